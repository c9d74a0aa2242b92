
import collections
import itertools
import math
import os

import pytest

from relpress.operators import compression
from relpress.plans import catalogue
from relpress.sources import workloads

DATA = "/root/testdata/sf0.001"
pytestmark = pytest.mark.skipif(not os.path.isdir(DATA), reason="no given tables here")

#: k, reduction, threshold, candidates, used, table rate in percent, mean length.
DENSE = [(0.2, "min", 18, 104, 6, 49.49, 2.0), (0.4, "min", 9, 118, 54, 68.16, 3.0), (0.4, "mean", 27, 44, 6, 49.49, 2.0), (0.6, "min", 3, 316, 54, 68.16, 3.0)]


@pytest.mark.parametrize("k, reduce, threshold, mined, used, rate, length", DENSE)
def test_dense(spark, k, reduce, threshold, mined, used, rate, length):
    c = compression.area_cover(workloads.relation(spark, DATA, workloads.dense()), k, reduce)
    r = c.report().first()
    assert (c.threshold, c.n_mined, r["n_used"], r["mean_len"]) == (threshold, mined, used, length)
    assert r["table_rate"] == pytest.approx(rate / 100, abs=1e-4) and r["compressed_share"] == 1.0


@pytest.mark.parametrize("objective, candidates, used, rate", [("savings", "all", 2, 24.92), ("savings", "paths", 2, 24.92), ("rate", "paths", 54, 68.16)])
def test_itemset_baselines(spark, objective, candidates, used, rate):
    r = compression.slices(workloads.relation(spark, DATA, workloads.dense()), 2, candidates, objective).report().first()
    assert r["n_used"] == used and r["table_rate"] == pytest.approx(rate / 100, abs=1e-4)


@pytest.mark.parametrize("sql, n", [(workloads.booleans_large(), 5883), (workloads.booleans_small(), 1265), (workloads.products(), 199), (workloads.labelled(), 102), (workloads.configurator(), 5995), (workloads.dense_quantity(), 5376)])
def test_sizes(spark, sql, n):
    assert workloads.relation(spark, DATA, sql).df.count() == n


def test_booleans_report_takes_the_automatic_threshold(spark, tmp_path):
    """Over few rows, closed sets are the intersections of rows; their frequencies give the threshold."""
    spark.read.parquet(f"{DATA}/lineitem.parquet").orderBy("l_orderkey", "l_linenumber").limit(14).write.parquet(f"{tmp_path}/lineitem.parquet")
    rel = workloads.relation(spark, str(tmp_path), workloads.booleans_large())
    rows = [frozenset(enumerate(r)) for r in rel.df.collect()]
    closed = set(rows)
    for r in rows:
        closed |= {c & r for c in closed}
    freqs = sorted((f for c in closed if c and (f := sum(c <= r for r in rows)) >= 2), reverse=True)
    for k in (0.2, 0.6):
        best = freqs[: math.ceil(k * len(rows))]
        want = {"min": min(best), "mean": math.ceil(sum(best) / len(best))}
        assert {r: compression.support_threshold(rel, k, r) for r in want} == want
    best = freqs[: math.ceil(0.2 * len(rows))]
    want = compression.area_cover(rel, s_min=math.ceil(sum(best) / len(best))).report().collect()
    assert catalogue.QUERIES["booleans_report"](spark, str(tmp_path)).collect() == want


def test_modular_workloads_report_has_every_slice_and_size(spark, monkeypatch):
    monkeypatch.setattr(catalogue, "MODULAR_SLICES", 2)
    monkeypatch.setattr(catalogue, "MODULAR_SIZES", (100, 5000, 7500))
    got = {(r["slice"], r["size"]): r for r in catalogue.QUERIES["modular_workloads_report"](spark, DATA).collect()}
    want = {(i, n): workloads.relation(spark, DATA, workloads.modular(n, 2, i)).df.count() for i in (0, 1) for n in (100, 5000, 7500)}
    assert {k: r["tuples"] for k, r in got.items()} == want and want[0, 100] == 100 and want[0, 5000] == want[0, 7500] > 1000
    alone = compression.area_cover(workloads.relation(spark, DATA, workloads.modular(5000, 2, 1)), 0.2, "mean").report().first()
    assert tuple(got[1, 7500])[2:] == tuple(alone)


def test_order_brands_of_every_length(spark):
    line, part = spark.read.parquet(f"{DATA}/lineitem.parquet"), spark.read.parquet(f"{DATA}/part.parquet")
    orders = collections.defaultdict(set)
    for r in line.join(part, line["l_partkey"] == part["p_partkey"]).select("l_orderkey", "p_brand").collect():
        orders[r[0]].add(r[1])
    counts = collections.Counter(s for o in orders.values() for n in range(1, len(o) + 1) for s in itertools.combinations(sorted(o), n))
    want = {(",".join(s), len(s), n) for s, n in counts.items() if n >= 5}
    assert max(n for _, n, _ in want) > 2
    assert {tuple(r) for r in catalogue.QUERIES["order_brands_frequent_all"](spark, DATA).collect()} == want
    pairs = {tuple(r) for r in catalogue.QUERIES["order_brands_frequent"](spark, DATA).collect()}
    assert pairs == {(s, f) for s, n, f in want if n <= 2}
