"""The experiments: problems in the shape of the published benchmarks over the given tables, solved and compressed.

Benchmarks: two boolean sets (18 and 15 columns), modular tables at four sizes, word grids in one and in all languages, and
a configurator of mixed arity. Relations are rows of (rel_id, vals), all of a benchmark in one table; every relation is
compressed, and every problem solved, in a task of its own. Runs are stored once for each folder of tables, and all reports
on solving read them.
"""

from __future__ import annotations

import io
from functools import reduce

import numpy as np
import pandas as pd
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from ..operators import local
from ..sources import workloads as W
from . import kernels, metrics
from .solving import packed, scattered, search_all
from .staging import ship, staged

#: Size and number of relations of the modular benchmarks: one relation has to hold enough tuples of the given tables.
MODULAR = {"modular2500": (2500, 20), "modular5000": (5000, 10), "modular7500": (7500, 7), "modular10000": (10000, 5)}
#: Grids of the word benchmarks: words down and words across.
GRIDS = ((3, 3), (3, 4), (4, 4), (4, 5))
WORD_LENGTHS = sorted({n for g in GRIDS for n in g})
BENCHMARKS = ("booleans18", "booleans15", *MODULAR, "words_en", "words_all", "configurator")
#: Variables (copies share the region at 20) and, by position, the number of values of the configurator's columns.
_PARTS = {"brand": 56, "kind": 26, "size": 51, "nation": 25, "segment": 26, "priority": 6, "status": 26, "flag": 26, "line": 26, "home": 25}


def workload_sql() -> dict[str, list[tuple[str, int, str]]]:
    """benchmark -> (SQL for the relation id, columns, source): {table} names a source."""
    out = {
        "booleans18": [("'booleans18'", 18, W.booleans_large(57971))],
        "booleans15": [("'booleans15'", 15, W.booleans_small())],
        "configurator": [(f"'{n}'", a, q) for n, a, q in W.configurator_parts()],
    }
    for name, (size, slices) in MODULAR.items():
        out[name] = [(f"concat('{name}_', which)", 7, W.modular_slices(size, slices))]
    for name, lang in (("words_en", "en"), ("words_all", None)):
        out[name] = [(f"'{name}_{n}'", n, ("words", n, lang)) for n in WORD_LENGTHS]
    return out


def _source(q, duckdb: bool = False) -> str:
    return W.words(q[1], q[2], duckdb) if isinstance(q, tuple) else q


def relations(spark: SparkSession, sf_dir: str, benchmarks: tuple[str, ...] = BENCHMARKS) -> DataFrame:
    """(rel_id, vals) of all relations of the benchmarks."""
    parts = []
    for b in benchmarks:
        for rel, a, q in workload_sql()[b]:
            df = W.rows(spark, sf_dir, _source(q))
            parts.append(df.select(F.expr(rel).alias("rel_id"), F.array(*[F.col(f"c{i}").cast("int") for i in range(a)]).alias("vals")))
    return reduce(DataFrame.unionByName, parts)


def _configurations(seed: int) -> list[tuple[str, list[int]]]:
    """Two configurations whose suppliers sit in one region, and what each must agree with."""
    out = []
    for at in (0, 10):
        out += [("parts", list(range(at, at + 10))), ("product", [at, at + 1, at + 2]), ("nation_region", [at + 3, 20]), ("nation_segment", [at + 9, at + 4]), ("status_priority", [at + 6, at + 5]), ("flag_status", [at + 7, at + 8])]
    return [*out, (f"brands{seed}", [0]), (f"brands{seed + 1}", [10]), (f"nations{seed}", [3]), (f"nations{seed + 1}", [13])]


def instances(benchmarks: tuple[str, ...] = BENCHMARKS, seeds: int = 2) -> list[dict]:
    """Problems: workload, id, domain sizes, constraints (rel_id, scope)."""
    out = []
    for b in benchmarks:
        if b in ("booleans18", "booleans15"):
            n, a = (133, 18) if b == "booleans18" else (2713, 15)
            out += [{"workload": b, "id": f"{b}_{s}", "sizes": [2] * 21, "constraints": [(b, x) for _, x in scattered(s, 21, n, a, 1)]} for s in range(seeds)]
        elif b in MODULAR:
            slices = MODULAR[b][1]
            # Forty variables; as many constraints as leave problems that propagation alone does not settle come second.
            for s in range(seeds):
                n = 40 if s % 2 == 0 else 8
                out.append({"workload": b, "id": f"{b}_{s}", "sizes": [8] * 40, "constraints": [(f"{b}_{r}", x) for r, x in scattered(s, 40, n, 7, slices)]})
        elif b == "configurator":
            out += [{"workload": b, "id": f"{b}_{s}", "sizes": [*list(_PARTS.values()) * 2, 5], "constraints": _configurations(s)} for s in range(seeds)]
        else:
            for down, across in GRIDS:
                rows = [(f"{b}_{across}", [r * across + c for c in range(across)]) for r in range(down)]
                cols = [(f"{b}_{down}", [r * across + c for r in range(down)]) for c in range(across)]
                out.append({"workload": b, "id": f"{b}_{down}x{across}", "sizes": [26] * (down * across), "constraints": rows + cols})
    return out


def listed(spark: SparkSession, seeds: int) -> DataFrame:
    """The configurator's one-column relations: which brands and supplier nations a customer accepts."""
    rows = [(f"brands{s}", [v]) for s in range(seeds + 1) for v in range(11, 56) if (v * 7 + s) % 3 != 0]
    rows += [(f"nations{s}", [v]) for s in range(seeds + 1) for v in range(25) if (v + s) % 2 == 0]
    return spark.createDataFrame(rows, "rel_id string, vals array<int>")


_STORED: dict[tuple, DataFrame] = {}


def runs(spark: SparkSession, sf_dir: str, benchmarks: tuple[str, ...] = BENCHMARKS, methods: tuple[str, ...] = tuple(kernels.METHODS), seeds: int = 2, time_limit_s: float = 2.0) -> DataFrame:
    """(method, workload, instance_id, status, nodes, cells, cpu_s, solution), run once for each session and folder."""
    key = (spark.sparkContext.applicationId, sf_dir, benchmarks, methods, seeds, time_limit_s)
    if key not in _STORED:
        every = relations(spark, sf_dir, benchmarks).unionByName(listed(spark, seeds))
        _STORED[key] = staged(search_all(every, instances(benchmarks, seeds), methods, time_limit_s), "runs")
    return _STORED[key]


# Compression ----------------------------------------------------------------------------------------------------------


def _all_sets(rows: np.ndarray, objective: str):
    sets = local.frequent(rows, 2)
    return local.choose(rows, sets, objective), len(sets), 2


def varied(rows: np.ndarray, k: float = 0.4, reduce: str = "mean", objective: str = "area", kind: str = "maximal", s_min: int | None = None):
    s = s_min or local.threshold(rows, k, reduce)
    sets = local.maximal(rows, s) if kind == "maximal" else local.frequent(rows, s)
    return local.choose(rows, sets, objective), len(sets), s


#: Readings of the compressors, and whether they take every frequent set, which wide relations have too many of.
READINGS = {
    "area_cover_mean": (lambda r: varied(r), False),
    "area_cover_min": (lambda r: varied(r, reduce="min"), False),
    "savings_paths": (lambda r: local.savings_slice(r, "savings"), False),
    "savings_best_path": (lambda r: (local.best_path(r), len(local.paths(r)), 2), False),
    "rate_paths": (lambda r: local.savings_slice(r, "rate"), False),
    "savings_all": (lambda r: _all_sets(r, "savings"), True),
    "rate_all": (lambda r: _all_sets(r, "rate"), True),
}
SWEEP = {f"k{int(100 * k)}_{r}": (lambda rows, k=k, r=r: varied(rows, k, r), False) for k in (0.2, 0.3, 0.4, 0.5, 0.6) for r in ("min", "mean")}
ABLATIONS = {f"objective_{o}": (lambda rows, o=o: varied(rows, objective=o), False) for o in local.SCORES}
ABLATIONS |= {"candidates_frequent": (lambda rows: varied(rows, kind="frequent"), True), "threshold_2": (lambda rows: varied(rows, s_min=2), False)}
#: Columns up to which readings over every frequent set are run.
ALL_SETS = 7

_REPORT = "tuples bigint, cells bigint, n_mined bigint, threshold bigint, n_used bigint, covered bigint, saved bigint, compressed_share double, table_rate double, mean_len double, mean_freq double"


def compressed(rels: DataFrame, readings: dict) -> DataFrame:
    """(method, rel_id, measures): each relation of (rel_id, vals) by each reading, a task each."""
    spark = rels.sparkSession
    ship(spark)
    blobs = packed(rels)
    methods = spark.createDataFrame([(m,) for m in readings], "method string")

    def run(key: tuple, group: pd.DataFrame) -> pd.DataFrame:
        method, rel_id = key
        rows = np.load(io.BytesIO(group["blob"].iloc[0])).astype(np.int64)
        reading, all_sets = readings[method]
        if all_sets and rows.shape[1] > ALL_SETS:
            return pd.DataFrame(columns=["method", "rel_id", *[x.split()[0] for x in _REPORT.split(", ")]])
        return pd.DataFrame([{"method": method, "rel_id": rel_id, **local.report(rows, *reading(rows))}])

    todo = blobs.crossJoin(F.broadcast(methods)).repartition(max(1, blobs.count() * len(readings)), "rel_id", "method")  # a few names; a task each
    return todo.groupBy("method", "rel_id").applyInPandas(run, f"method string, rel_id string, {_REPORT}")


def details(measured: DataFrame) -> DataFrame:
    """Means over the relations of each benchmark and method."""
    name = F.regexp_replace("rel_id", "_[0-9]+$", "")
    share = [F.round(F.avg(c), 6).alias(c) for c in ("compressed_share", "table_rate", "n_mined", "n_used", "mean_len", "mean_freq", "threshold")]
    return measured.groupBy(name.alias("benchmark"), "method").agg(F.count("*").alias("relations"), F.max("tuples").alias("max_tuples"), *share)


# Queries --------------------------------------------------------------------------------------------------------------

QUERIES = {}
ORACLE_SQL = {}


def _query(f):
    QUERIES[f.__name__] = f
    return f


@_query
def search_solved(spark, sf):
    """Every method on every problem of all benchmarks, two seconds of CPU each; equal consistency gives equal nodes."""
    return runs(spark, sf).select("method", "workload", "instance_id", "status", "nodes", "cells", "cpu_s")


@_query
def solved_summary(spark, sf):
    """Problems, problems solved, and mean seconds of the solved, by benchmark and method."""
    return metrics.solved(runs(spark, sf), "workload")


@_query
def cactus_curve(spark, sf):
    """The cumulative curve of cells looked at over all benchmarks; unlike seconds it is the same in every run."""
    return metrics.cactus(runs(spark, sf), "cells")


@_query
def cactus_curve_seconds(spark, sf):
    return metrics.cactus(runs(spark, sf), "cpu_s")


@_query
def cactus_curve_benchmarks(spark, sf):
    """Curves of single benchmarks: word grids in all languages and in one, and the largest modular tables."""
    return metrics.cactus(runs(spark, sf).where(F.col("workload").isin("words_all", "words_en", "modular10000")), "cells", "workload")


@_query
def curve_crossings(spark, sf):
    """Where the entry filter's curve crosses that of every other method."""
    curve = staged(metrics.cactus(runs(spark, sf), "cells"), "curve")
    others = [m for m in kernels.METHODS if m != "entries"]
    return reduce(DataFrame.unionByName, [metrics.dominance(curve, "entries", m).select(F.lit(m).alias("against"), "solved", "lead") for m in others])


@_query
def reduction_variants(spark, sf):
    """Tabular reduction and its variants only: solved problems, nodes and cells."""
    r = runs(spark, sf).where(F.col("method").isin("tabular_plain", "tabular", "short", "entries", "entries_slices"))
    return r.groupBy("workload", "method").agg(F.count_if(F.col("status") != "timeout").alias("solved"), F.sum("nodes").alias("nodes"), F.sum("cells").alias("cells"))


@_query
def compression_details(spark, sf):
    """Shares, candidates, entries, lengths and frequencies of every benchmark by every compressor's reading."""
    rels = relations(spark, sf, tuple(b for b in BENCHMARKS if b != "configurator"))
    longer = reduce(DataFrame.unionByName, [W.rows(spark, sf, W.words(n, lang)).select(F.lit(f"{name}_{n}").alias("rel_id"), F.array(*[F.col(f"c{i}").cast("int") for i in range(n)]).alias("vals")) for name, lang in (("words_en", "en"), ("words_all", None)) for n in (6, 8)])
    return details(compressed(rels.unionByName(longer), READINGS))


@_query
def threshold_shares(spark, sf):
    """Thresholds from 20 to 60 % of the tuples, least and mean, on modular tables and words."""
    return details(compressed(relations(spark, sf, ("modular2500", "words_en")), SWEEP))


@_query
def choice_ablations(spark, sf):
    """What the objective, the kind of candidates and the threshold do, on modular tables and words."""
    return details(compressed(relations(spark, sf, ("modular2500", "words_en")), ABLATIONS))


def _shape() -> dict[str, tuple[int, int, int, int, int, int]]:
    """benchmark -> instances, most variables, values, relations, columns, constraints."""
    out = {}
    for b in BENCHMARKS:
        every = instances((b,))
        columns = max(len(s) for x in every for _, s in x["constraints"])
        out[b] = (len(every), max(len(x["sizes"]) for x in every), max(max(x["sizes"]) for x in every), max(len({r for r, _ in x["constraints"]}) for x in every), columns, max(len(x["constraints"]) for x in every))
    return out


@_query
def benchmark_characteristics(spark, sf):
    """Instances, and the most variables, values, relations, tuples, columns and constraints of each benchmark."""
    rels = staged(relations(spark, sf).unionByName(listed(spark, 2)).groupBy("rel_id").agg(F.count("*").alias("tuples")), "sizes")
    problems = instances()
    variables = spark.createDataFrame([(x["workload"], x["id"], v, n) for x in problems for v, n in enumerate(x["sizes"])], "workload string, instance_id string, var int, n int")
    domains = variables.select("instance_id", "var", F.explode(F.sequence(F.lit(0), F.col("n") - 1)).alias("code"))
    constraints = spark.createDataFrame([(x["id"], i, r, len(s)) for x in problems for i, (r, s) in enumerate(x["constraints"])], "instance_id string, cid int, rel_id string, arity int")
    return metrics.characteristics(variables.select("workload", "instance_id", "var"), domains, constraints, rels)


def _most_tuples(b: str) -> str:
    """SQL for the size of the largest relation that the benchmark's problems use."""
    used = {r for x in instances((b,)) for r, _ in x["constraints"]}
    counts = []
    for rel, _, q in workload_sql()[b]:
        if "which" in rel:
            at = ", ".join(r.rpartition("_")[2] for r in sorted(used))
            counts.append(f"SELECT count(*) AS n FROM ({W.plain(_source(q, True))}) AS t WHERE which IN ({at}) GROUP BY which")
        elif rel.strip("'") in used:
            counts.append(f"SELECT count(*) AS n FROM ({W.plain(_source(q, True))}) AS t")
    return f"(SELECT max(n) FROM ({' UNION ALL '.join(counts)}))"


ORACLE_SQL["benchmark_characteristics"] = " UNION ALL ".join(
    f"SELECT '{b}' AS workload, {i} AS instances, {v} AS max_vars, {n} AS max_values, {r} AS max_relations, {_most_tuples(b)} AS max_tuples, {c} AS max_columns, {k} AS max_constraints" for b, (i, v, n, r, c, k) in _shape().items()
)
