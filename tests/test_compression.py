import random

import numpy as np
import pytest

from relpress.functions.itemsets import mask_of, register
from relpress.model import CompressedRelation, Relation
from relpress.operators import compression, mining, selection

from .fixtures import EXAMPLE, X, example


def heads_of(c):
    return {(tuple((x["p"], x["v"]) for x in r["items"]), r["freq"]) for r in c.heads.collect()}


def test_example_full(spark):
    for overlap in ("drop", "shrink"):
        c = compression.area_cover(example(spark), s_min=2, overlap=overlap)
        assert heads_of(c) == {
            (((0, 1), (1, 1), (2, 2)), 3),
            (((0, 0), (1, 0), (2, 0), (4, 2)), 2),
            (((0, 0), (1, 0), (2, 1), (4, 2)), 2),
            (((0, 0), (3, 2), (4, 0)), 2),
            (((0, 1), (1, 0), (2, 2)), 2),
        }
        assert c.default.count() == 0 and c.n_mined == 11
        r = c.report().first()
        assert (r["cells"], r["saved"], r["compressed_share"], r["mean_len"], r["mean_freq"]) == (55, 20, 1.0, 3.4, 2.2)
        assert r["table_rate"] == pytest.approx(20 / 55, abs=1e-6)
        assert {tuple(x) for x in c.expand().collect()} == set(EXAMPLE)


def test_example_printed_six(spark):
    """Fed with the first six ranked sets only, four entries and two default rows remain."""
    rel = example(spark)
    ranked = selection.rank(mining.maximal(mining.frequent(rel, 2)), 5)
    first = [r["rank"] for r in ranked.orderBy("rank").limit(6).collect()]
    tuples = rel.numbered()
    sets = ranked.where(ranked["rank"].isin(first))
    chosen, _ = selection.greedy(sets, selection.cover(sets, tuples))
    c = compression.build(rel, tuples, sets, chosen)
    assert c.heads.count() == 4 and c.report().first()["saved"] == 17
    assert {tuple(x["v"] for x in r["items"]) for r in c.default.collect()} == {EXAMPLE[6], EXAMPLE[7]}


def test_single_entry(spark):
    found = compression.entry(example(spark), {"x0": 0, "x1": 0, "x2": 1})
    assert {tuple(r) for r in found.collect()} == {(1, 2), (2, 0), (3, 2)}


@pytest.mark.parametrize("overlap", ["drop", "shrink"])
def test_parallel_choice_is_the_sequential_one(spark, overlap):
    rng = random.Random(overlap)
    for _ in range(2):
        rows = list({tuple(rng.randrange(3) for _ in range(4)) for _ in range(30)})
        rel = Relation.of(spark.createDataFrame(rows, "a int, b int, c int, d int"))
        ranked = selection.rank(mining.maximal(mining.frequent(rel, 2)), 4)
        covers = selection.cover(ranked, rel.numbered())
        chosen, _ = selection.greedy(ranked, covers, overlap, 4)
        names = {r["rank"]: (tuple((x["p"], x["v"]) for x in r["items"]), r["len"]) for r in ranked.collect()}
        held: dict = {}
        for r in covers.collect():
            held.setdefault(r["rank"], set()).add(r["tid"])
        want = selection.greedy_local(names, held, overlap)
        got: dict = {}
        for r in chosen.collect():
            got.setdefault(names[r["rank"]][0], set()).add(r["tid"])
        assert got == dict(want)


def test_invariants(spark):
    rng = random.Random(9)
    rows = list({tuple(rng.randrange(4) for _ in range(5)) for _ in range(60)})
    rel = Relation.of(spark.createDataFrame(rows, ", ".join(f"{c} int" for c in X)))
    for build in (lambda: compression.area_cover(rel, 0.4, "mean"), lambda: compression.savings_slice(rel), lambda: compression.rate_tree(rel), lambda: compression.microstructure(rel), lambda: compression.area_cover(rel, 0.4, objective="freq")):
        c = build()
        assert {tuple(x) for x in c.expand().collect()} == set(rows)
        assert c.heads.where("freq < 2").count() == 0
        assert c.body.count() + c.default.count() == len(rows)
        assert c.body.select("tid").distinct().count() == c.body.count()


def test_products_and_wildcards(spark):
    full = Relation.of(spark.createDataFrame([(a, b, c) for a in (0, 1) for b in (0, 1) for c in (0, 1)], "a int, b int, c int"))
    assert [tuple(map(tuple, r)) for r in compression.cartesian(full).collect()] == [((0, 1), (0, 1), (0, 1))]
    w = compression.wildcard(full).collect()
    assert len(w) == 1 and tuple(w[0]) == (None, None, None, 7)
    rel = example(spark)
    rows = set()
    for r in compression.cartesian(rel).collect():
        part = [()]
        for values in r:
            part = [(*p, v) for p in part for v in values]
        assert not rows & set(part)
        rows |= set(part)
    assert rows == set(EXAMPLE)


def test_diagram_paths_are_the_tuples(spark):
    for automaton in (False, True):
        edges = compression.diagram(example(spark), automaton=automaton).collect()
        out: dict = {}
        for e in edges:
            out.setdefault((e["level"], e["node"]), []).append((e["code"], e["child"]))
        paths, (root,) = set(), {k for k in out if k[0] == 0}
        stack = [(root, ())]
        while stack:
            (level, node), path = stack.pop()
            for code, child in out[level, node]:
                if level == 4:
                    paths.add((*path, code))
                else:
                    stack.append(((level + 1, child), (*path, code)))
        assert paths == set(EXAMPLE)


def test_write_and_read(spark, tmp_path):
    c = compression.area_cover(example(spark), s_min=2)
    c.write(str(tmp_path / "c"))
    back = CompressedRelation.read(spark, str(tmp_path / "c"))
    assert {tuple(x) for x in back.expand().collect()} == set(EXAMPLE) and (back.n_mined, back.threshold) == (11, 2)
    assert {tuple(x) for x in back.where({1: lambda v: v != 0}).collect()} == {r for r in EXAMPLE if r[1] != 0}


def test_codes_and_null(spark):
    rel, words = Relation.of(spark.createDataFrame([("b", None), ("a", 1.5), (None, 1.5)], "s string, d double")).coded()
    assert {tuple(r) for r in rel.df.collect()} == {(2, 0), (1, 1), (0, 1)}
    assert words.where("var = 0").count() == 3


def test_empty_and_tiny(spark):
    for rows in ([], [(1, 2, 3, 4, 5)]):
        rel = Relation(spark.createDataFrame(rows, ", ".join(f"{c} int" for c in X)), X)
        c = compression.area_cover(rel, 0.4, "mean")
        assert c.heads.count() == 0 and {tuple(x) for x in c.expand().collect()} == set(rows)
        assert c.report().first()["table_rate"] == 0


def test_sql_functions(spark):
    register(spark)
    row = spark.sql("SELECT itemset_area(3, 3L) AS a, entry_saving(3, 3L) AS s, entry_rate(3, 3L, 5) AS r, mask_length(7L) AS m").first()
    assert tuple(row) == (9, 6, 0.4, 3)
    sets = mining.frequent(example(spark), 2).select(mask_of(mining.F.col("items")).alias("mask"), "len")
    assert sets.where("mask_length(mask) <> len").count() == 0


def test_choice_by_bit_vectors_is_the_choice_by_rows(spark, monkeypatch):
    """Over several blocks, and through ``choose`` without any cover by rows."""
    rng = np.random.default_rng(3)
    rows = sorted({tuple(int(x) for x in r) for r in rng.integers(0, 2, (400, 9))})
    rel = Relation(spark.createDataFrame(rows, ", ".join(f"c{i} int" for i in range(9))), [f"c{i}" for i in range(9)])
    sets, tuples = selection.rank(compression.candidates(rel, 12), 9), rel.numbered()
    want, _ = selection.greedy(sets, selection.cover(sets, tuples))
    monkeypatch.setattr(selection, "BLOCK", 50)
    got, rounds = selection.greedy_bits(sets, tuples)
    want = {(r["rank"], r["tid"], str(r["head"])) for r in want.collect()}
    assert {(r["rank"], r["tid"], str(r["head"])) for r in got.collect()} == want and rounds > 1 and len({w[0] for w in want}) > 3
    monkeypatch.setattr(compression, "DENSE_SETS", 1)
    monkeypatch.setattr(selection, "cover", None)
    c = compression.choose(rel, sets.select("items", "len", "freq"), "area")
    assert sorted(map(tuple, c.expand().collect())) == rows and c.heads.count() == len({w[0] for w in want})
