import pytest

from relpress.operators import compression, filters
from relpress.plans import metrics, solving

from .fixtures import EXAMPLE, X, example

REMOVALS = [{1: [0]}, {0: [1], 3: [1]}, {4: [2]}, {2: [0, 1, 2]}, {3: [9]}]


def supported(removed):
    ok = [r for r in EXAMPLE if not any(r[p] in c for p, c in removed.items())]
    return {(p, v) for r in ok for p, v in enumerate(r)}


@pytest.mark.parametrize("removed", REMOVALS)
def test_all_filters_agree(spark, removed):
    rel = example(spark)
    tuples = rel.numbered()
    domains = filters.restrict(rel.domains(), removed).cache()
    gone = spark.createDataFrame([(p, v) for p, c in removed.items() for v in c], "var int, code int")
    bits = compression.bitset(compression.dense(rel))
    found = {
        "scan": filters.scan(tuples, domains, 5),
        "settled": filters.settled(tuples, domains, 5, list(removed)),
        "dual": filters.dual(tuples, gone),
        "counters": filters.counters(tuples, gone),
        "reset": filters.counters(tuples, gone, "auto"),
        "residues": filters.residues(tuples, domains, 5, filters.residues_of(tuples)),
        "lists": filters.bitset(bits, domains, 5, None, "lists"),
        "current": filters.bitset(bits, domains, 5, list(removed), "current"),
        "diagram": filters.diagram(compression.diagram(rel), 5, domains),
        "entries": filters.entries(compression.area_cover(rel, s_min=2), domains)[0],
    }
    if all(len(c) < 3 for c in removed.values()):
        found |= {
            "cartesian": filters.cartesian(compression.cartesian(rel), X, domains),
            "wildcard": filters.wildcard(compression.wildcard(rel), X, domains),
            "restricted": filters.restricted(compression.restricted(rel), X, domains),
        }
    want = supported(removed)
    assert {k: {(r["var"], r["code"]) for r in f.collect()} for k, f in found.items()} == dict.fromkeys(found, want)


def test_event_of_the_example(spark):
    """Removing 0 from the second column leaves 8, 9, 10 and 2 alive, and two entries."""
    rel = example(spark)
    c = compression.area_cover(rel, s_min=2)
    domains = filters.restrict(rel.domains(), {1: [0]})
    found, state = filters.entries(c, domains)
    assert {(r["var"], r["code"]) for r in found.collect()} == {(0, 0), (0, 1), (1, 1), (1, 2), (2, 0), (2, 2), (3, 0), (3, 2), (3, 3), (4, 0), (4, 1), (4, 2)}
    assert sorted((r["live"], r["rows"]) for r in state.where("entry >= 0").collect()) == [(0, 2), (0, 2), (0, 2), (1, 2), (3, 3)]
    rows = filters.mark(rel.numbered().selectExpr("*", "cast(null as int) AS dead_at"), domains, 5, 1)
    assert rows.where("dead_at IS NULL").count() == 4 and filters.restore(rows, 0).where("dead_at IS NULL").count() == 11
    w = filters.work(c, domains).first()
    assert w["entry_cells"] < w["flat_cells"] == 55


def test_large_domains_go_by_joins(spark, monkeypatch):
    monkeypatch.setattr(filters, "DOMAIN_VALUES", 3)
    rel = example(spark)
    assert {(r["var"], r["code"]) for r in filters.scan(rel.numbered(), filters.restrict(rel.domains(), {1: [0]}), 5).collect()} == supported({1: [0]})


def test_solving_agrees(spark):
    rel = example(spark)
    constraints = [(rel, [0, 1, 2, 3, 4]), (rel, [0, 5, 2, 6, 4])]
    sizes = [2, 3, 3, 4, 3, 3, 4]
    solutions = {tuple(r) for r in solving.by_join(constraints).collect()}
    want = {(*a[:5], b[1], b[3]) for a in EXAMPLE for b in EXAMPLE if (a[0], a[2], a[4]) == (b[0], b[2], b[4])}
    assert solutions == want
    domains = spark.createDataFrame([(v, c) for v, n in enumerate(sizes) for c in range(n)], "var int, code int")
    assert {tuple(r) for r in solving.frontier(constraints, domains).collect()} == want
    assert solving.check(constraints, solving.by_join(constraints)).count() == len(want)
    live, rounds = solving.propagate(constraints, domains)
    assert rounds >= 1 and {(v, s[v]) for s in want for v in range(7)} <= {(r["var"], r["code"]) for r in live.collect()}
    runs = solving.search(spark, [("yes", sizes, [(0, s) for _, s in constraints]), ("no", [2, 1, 1, 1, 1], [(0, [0, 1, 2, 3, 4])])], [rel], ("tabular", "entries", "entries_slices", "bits"), 60)
    rows = runs.collect()
    assert {(r["instance_id"], r["status"]) for r in rows} == {("yes", "sat"), ("no", "unsat")} and all(tuple(r["solution"]) in want for r in rows if r["status"] == "sat")
    assert len({r["nodes"] for r in rows if r["instance_id"] == "yes"}) == 1
    assert {r["solved"] for r in metrics.solved(runs).collect()} == {2}


def test_wipe_out_empties_all(spark):
    rel = example(spark)
    domains = rel.domains().where("NOT (var = 2 AND code = 2) AND NOT (var = 0 AND code = 0)").select("var", "code")
    live, _ = solving.propagate([(rel, [0, 1, 2, 3, 4])], domains)
    assert live.count() == 0


def test_curves(spark):
    runs = spark.createDataFrame([("a", "1", "sat", 5.0), ("a", "2", "unsat", 1.0), ("a", "3", "timeout", 9.0), ("b", "1", "sat", 2.0), ("b", "2", "sat", 3.0)], "method string, instance_id string, status string, cpu_s double")
    curve = metrics.cactus(runs).cache()
    assert {(r["method"], r["solved"], r["total"]) for r in curve.collect()} == {("a", 1, 1.0), ("a", 2, 6.0), ("b", 1, 2.0), ("b", 2, 5.0)}
    assert [tuple(r) for r in metrics.dominance(curve, "a", "b").orderBy("solved").collect()] == [(1, -1), (2, 1)]
    s = {r["method"]: (r["instances"], r["solved"], r["mean_cpu_s"]) for r in metrics.solved(runs).collect()}
    assert s == {"a": (3, 2, 3.0), "b": (2, 2, 2.5)}
