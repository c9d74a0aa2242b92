"""Search kernels, in-task compressors, kept filter states, tables of forbidden tuples and the experiments' shapes."""

import itertools
import os
import random

import numpy as np
import pytest
from pyspark.sql import functions as F

from relpress.model import Constraint, Instance, Relation
from relpress.operators import compression, filters, local, mining, selection, stateful
from relpress.plans import experiments, kernels, solving

from .fixtures import EXAMPLE, X, brute_closed, brute_frequent, example, sets_of

DATA = "/root/testdata/sf0.001"


def rows_of(seed, n=60, arity=5, values=4):
    rng = random.Random(seed)
    return sorted({tuple(rng.randrange(values if p else 2) for p in range(arity)) for _ in range(n)})


@pytest.mark.parametrize("method", kernels.METHODS)
def test_kernels_filter_alike(method):
    """A chain of removals and a way back: what each kernel supports is what valid tuples hold."""
    for seed in range(6):
        rng = random.Random(seed)
        rows, sizes = rows_of(seed), [2, 4, 4, 4, 4]
        table = kernels.build(method, np.array(rows), sizes)
        live = {p: np.ones(n, bool) for p, n in enumerate(sizes)}
        states = [(table.filter(table.start(), live, list(range(5)), list(range(5)))[0], live)]
        for _ in range(5):
            state, live = states[rng.randrange(len(states))]
            live = {p: d.copy() for p, d in live.items()}
            changed = rng.sample(range(5), 2)
            for p in changed:
                live[p][rng.randrange(sizes[p])] = False
            ok = [r for r in rows if all(live[p][v] for p, v in enumerate(r))]
            state, found = table.filter(state, live, sorted(changed), list(range(5)))
            want = {p: {r[p] for r in ok} for p in range(5)}
            assert {p: set(np.flatnonzero(found[p] & live[p])) for p in range(5)} == want
            if ok:  # the search keeps domains at what is supported
                states.append((state, {p: live[p] & found[p] for p in live}))
                states[-1] = (table.filter(state, states[-1][1], list(range(5)), [])[0], states[-1][1])


def test_kernels_search_alike(spark):
    rng = random.Random(3)
    rel = {f"r{i}": rows_of(i, 70) for i in range(2)}
    relations = spark.createDataFrame([(k, list(r)) for k, rows in rel.items() for r in rows], "rel_id string, vals array<int>")
    problems = [{"workload": "w", "id": str(i), "sizes": [2, *[4] * 6], "constraints": [(f"r{j % 2}", [0, *rng.sample(range(1, 7), 4)]) for j in range(2 + i)]} for i in range(4)]
    runs = solving.search_all(relations, problems, tuple(kernels.METHODS), 60).collect()
    assert len(runs) == 4 * len(kernels.METHODS)
    for p in problems:
        here = [r for r in runs if r["instance_id"] == p["id"]]
        every = [v for v in itertools.product(*map(range, p["sizes"])) if all(tuple(v[x] for x in s) in set(rel[r]) for r, s in p["constraints"])]
        assert {(r["status"], r["nodes"]) for r in here} == {("sat" if every else "unsat", here[0]["nodes"])}
        assert all(tuple(r["solution"]) in every for r in here if every)
    late = solving.search_all(relations, problems[:1], ("tabular",), -1.0).first()
    assert late["status"] == "timeout" and late["solution"] is None


@pytest.mark.parametrize("seed", [1, 2])
def test_local_forms_are_those_of_the_cluster(spark, seed):
    rows = rows_of(seed, 90, 4, 3)
    rel = Relation(spark.createDataFrame(rows, "a int, b int, c int, d int"), list("abcd"))
    a = local.ordered(np.array(rows))

    def entries(found):
        return {(s, len(t)) for s, t in found}

    for reduce in ("min", "mean"):
        c = compression.area_cover(rel, 0.4, reduce)
        found, mined, s = local.area_cover(a, 0.4, reduce)
        assert (entries(found), mined, s) == (sets_of(c.heads), c.n_mined, c.threshold)
        report = c.report().first().asDict()
        assert {k: v for k, v in local.report(a, found, mined, s).items() if k in report} == pytest.approx(report)
    for objective in ("savings", "rate"):
        assert entries(local.savings_slice(a, objective)[0]) == sets_of(compression.slices(rel, 2, "paths", objective).heads)
    sets = lambda r: tuple(tuple(r[c]) for c in rel.scope)
    assert set(local.products(a)) == {sets(r) for r in compression.cartesian(rel).collect()}
    sizes = [len(set(x)) for x in zip(*rows)]
    short = {(r["any"], *[-1 if r[c] is None else r[c] for c in rel.scope]) for r in compression.wildcard(rel).collect()}
    assert {tuple(x) for x in local.wildcards(a, sizes)} == short
    edges = compression.diagram(rel).groupBy("level").agg(F.countDistinct("node").alias("n"), F.count("*").alias("e")).collect()
    mine = local.diagram(a)
    assert {(r["level"], r["n"], r["e"]) for r in edges} == {(k, len(set(mine[mine[:, 0] == k, 1])), int((mine[:, 0] == k).sum())) for k in range(4)}


def test_best_paths_cover_without_overlap():
    rows = local.ordered(np.array(rows_of(5, 120)))
    found = local.best_path(rows)
    places = np.concatenate([t for _, t in found])
    assert len(places) == len(set(places.tolist())) and all(len(t) > 1 and all(rows[i][p] == v for i in t for p, v in s) for s, t in found)


def test_top_closed_is_the_top(spark):
    rows = rows_of(8, 80, 5, 3)
    rel = Relation(spark.createDataFrame(rows, ", ".join(f"{c} int" for c in X)), X)
    want = sorted((f for _, f in brute_closed(brute_frequent(rows, 2))), reverse=True)
    for most_rows in (200_000, 8):
        for k in (3, 20, 10_000):
            found = mining.top_closed_shards(rel, k, 2, most_rows)
            assert sorted((r["freq"] for r in found.collect()), reverse=True)[:k] == want[:k]
    assert compression.support_threshold(rel, 20, "min") == want[19] and compression.support_threshold(rel, 20, "mean") == -(-sum(want[:20]) // 20)


def test_covers_by_either_way(spark):
    rel = example(spark)
    ranked = selection.rank(mining.frequent(rel, 2), 5)
    tuples = rel.numbered()
    one, two = selection.cover(ranked, tuples), selection._cover_by_rarest(ranked.select("rank", "items"), tuples)
    assert sorted(map(tuple, one.collect())) == sorted(map(tuple, two.collect())) and two.count() == ranked.agg(F.sum("freq")).first()[0]


def test_tables_of_forbidden_tuples(spark):
    def table(rows, *cols):
        return Relation(spark.createDataFrame(rows, ", ".join(f"{c} int" for c in cols)), list(cols), sign=False)

    two = Instance({0: [0, 1], 1: [0, 1]}, [Constraint(table([(0, 0)], "a", "b"), [0, 1])])
    assert {tuple(r) for r in two.propagate(spark).collect()} == {(0, 0), (0, 1), (1, 0), (1, 1)}
    assert {tuple(r) for r in two.solve_by_join(spark).collect()} == {(0, 1), (1, 0), (1, 1)}
    assert tuple(two.solve(spark).first()["solution"]) in {(0, 1), (1, 0), (1, 1)}
    # Values other than 0 to n - 1, a table of each sign, a variable that no table of allowed tuples holds, and one that stands twice.
    allowed = Relation(spark.createDataFrame([(3, 7), (5, 7), (5, 9)], "a int, b int"), ["a", "b"])
    no = [(5, 7), (3, 7), (8, 9)]
    mixed = Instance({1: [3, 5], 2: [7, 9], 4: [2, 7, 9]}, [Constraint(allowed, [1, 2]), Constraint(table([(5, 9, 2), (5, 9, 7), (5, 7, 7)], "x", "y", "z"), [1, 2, 4]), Constraint(table(no, "p", "q"), [1, 2]), Constraint(table([(9, 9)], "s", "t"), [4, 4])])
    want = {(a, b, c) for a, b in [(3, 7), (5, 7), (5, 9)] for c in (2, 7, 9) if (a, b, c) not in {(5, 9, 2), (5, 9, 7), (5, 7, 7)} and (a, b) not in no and c != 9}
    assert {tuple(r) for r in mixed.solve_by_join(spark).collect()} == want == set()
    less = Instance(mixed.domains, mixed.constraints[:3])
    want = {(5, 9, 9)}
    assert {tuple(r) for r in less.solve_by_join(spark).collect()} == want and tuple(less.solve(spark, ("tabular", "bits")).first()["solution"]) == (5, 9, 9)
    assert {tuple(r) for r in less.propagate(spark).collect()} == {(1, 5), (2, 9), (4, 9)} and less.solve(spark).first()["status"] == "sat"
    domains = less.domain_table(spark)
    assert {tuple(r) for r in solving.frontier(less._parts(), domains).collect()} == want
    assert solving.check(less._parts(), less.solve_by_join(spark)).count() == 1


REMOVALS = [{1: [0]}, {0: [1], 3: [1]}, {4: [2]}, {3: [9], 2: [1, 2]}]


@pytest.mark.parametrize("removed", REMOVALS[:2])
def test_filters_beyond_a_predicate(spark, monkeypatch, removed):
    """With too many live values for a predicate every filter joins, to the same result."""
    rel = example(spark)
    domains = filters.restrict(rel.domains(), removed)
    area = compression.area_cover(rel, s_min=2)

    def all_of():
        found = {
            "scan": filters.scan(rel.numbered(), domains, 5),
            "settled": filters.settled(rel.numbered(), domains, 5, list(removed)),
            "residues": filters.residues(tuples := rel.numbered(), domains, 5, filters.residues_of(tuples)),
            "entries": filters.entries(area, domains)[0],
            "slices": filters.entries(compression.savings_slice(rel), domains)[0],
            "cartesian": filters.cartesian(compression.cartesian(rel), X, domains),
            "wildcard": filters.wildcard(compression.wildcard(rel), X, domains),
            "restricted": filters.restricted(compression.restricted(rel), X, domains),
        }
        marked = filters.mark(rel.numbered().withColumn("dead_at", F.lit(None).cast("int")), domains, 5, 3)
        work = tuple(filters.work(area, domains).first())
        state = sorted(map(tuple, filters.entries(area, domains)[1].select("live", "rows").collect()))
        return {k: {(r["var"], r["code"]) for r in f.collect()} for k, f in found.items()}, marked.where("dead_at = 3").count(), filters.restore(marked, 2).where("dead_at IS NULL").count(), work, state

    want = all_of()
    assert len(set(map(frozenset, want[0].values()))) == 1
    monkeypatch.setattr(filters, "DOMAIN_VALUES", 3)
    assert all_of() == want


@pytest.mark.parametrize("method", ["lists", "counters", "counters_reset", "bits", "diagram", "entries", "entries_slices"])
def test_kept_states(spark, method):
    """Removals at falling depths, a way back, and on from there: each answer is that of a scan from the start."""
    rel = example(spark)
    state, gone = stateful.kept(rel, method, 0.4), {}

    def scan(removed):
        ok = [r for r in EXAMPLE if not any(r[p] in c for p, c in removed.items())]
        return {(p, v) for r in ok for p, v in enumerate(r)}

    path = [(0, {})]
    for depth, event in ((1, {1: [0]}), (2, {4: [0], 3: [3]}), (-1, {}), (2, {2: [2]}), (3, {0: [0]})):
        if depth < 0:
            state.back(1)
            path = path[:2]
            assert {tuple(r) for r in state.supported().collect()} == scan(path[-1][1])
            continue
        rows = spark.createDataFrame([(p, v) for p, c in event.items() for v in c], "var int, code int")
        gone = {p: path[-1][1].get(p, []) + event.get(p, []) for p in {*path[-1][1], *event}}
        path.append((depth, gone))
        assert {tuple(r) for r in state.remove(rows, depth).collect()} == scan(gone)


@pytest.mark.skipif(not os.path.isdir(DATA), reason="no given tables here")
def test_benchmarks_have_their_relations(spark):
    """Every constraint names a relation that exists and fits its scope; kernels agree on the problems they finish."""
    rels = experiments.relations(spark, DATA).unionByName(experiments.listed(spark, 2)).groupBy("rel_id").agg(F.max(F.size("vals")).alias("a"), F.max(F.array_max("vals")).alias("v")).collect()
    width = {r["rel_id"]: (r["a"], r["v"]) for r in rels}
    for x in experiments.instances():
        for r, scope in x["constraints"]:
            assert width[r][0] == len(scope) == len(set(scope)) and width[r][1] < max(x["sizes"][v] for v in scope)
    runs = experiments.runs(spark, DATA, ("modular2500", "words_en"), ("tabular", "bits", "diagram_reset", "entries"), 2, 30.0).collect()
    nodes = {}
    for r in runs:
        if r["status"] != "timeout":
            nodes.setdefault(r["instance_id"], set()).add((r["status"], r["nodes"]))
    assert nodes and all(len(n) == 1 for n in nodes.values())
