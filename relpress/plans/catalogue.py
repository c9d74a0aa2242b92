"""Registered queries over the given tables and, where SQL can say the same, their DuckDB oracles."""

from __future__ import annotations

from collections.abc import Callable
from functools import reduce

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F
from pyspark.sql.window import Window

from ..functions.itemsets import as_items, saving, spread
from ..model import Constraint, Instance, Relation
from ..operators import compression, filters, mining, selection, stateful
from ..sources import workloads as W
from ..streaming import events as streams
from . import experiments, metrics, solving
from .staging import staged

Query = Callable[[SparkSession, str], DataFrame]

#: Support thresholds of the mining queries; k of the automatic threshold; values removed in the filter queries (var -> codes).
S_FREQ, S_CLOSED, K = 20, 9, 0.4
REMOVED = {0: [65], 2: [0, 1, 2, 3], 3: [5]}
COLS = ["c0", "c1", "c2", "c3"]


def _rel(spark: SparkSession, sf_dir: str, sql: str | None = None) -> Relation:
    return W.relation(spark, sf_dir, sql or W.dense())


def _flat(sets: DataFrame, cols: list[str] = COLS) -> DataFrame:
    return sets.select(*spread(F.col("items"), cols), F.col("len").cast("int").alias("len"), F.col("freq").cast("bigint").alias("freq"))


# SQL building blocks --------------------------------------------------------------------------------------------------


def _with(*ctes: tuple[str, str], recursive: bool = False) -> str:
    return f"WITH {'RECURSIVE ' if recursive else ''}" + ", ".join(f"{n} AS ({q})" for n, q in ctes)


def _rel_cte(sql: str | None = None) -> tuple[str, str]:
    return "rel", W.plain(sql or W.dense())


def _sets_cte(a: int = 4, least: int = 2) -> tuple[str, str]:
    """Every itemset with frequency, by cube."""
    cols = [f"c{i}" for i in range(a)]
    mask = " + ".join(f"(1 - GROUPING(c{i})) * {1 << i}" for i in range(a))
    size = " + ".join(f"(1 - GROUPING(c{i}))" for i in range(a))
    return "sets", f"SELECT * FROM (SELECT {', '.join(cols)}, {mask} AS mask, CAST({size} AS INT) AS len, count(*) AS freq FROM rel GROUP BY CUBE ({', '.join(cols)})) WHERE mask > 0 AND freq >= {least}"


def _sub(a: int) -> str:
    """t is a proper superset of s."""
    same = " AND ".join(f"(s.c{i} IS NULL OR s.c{i} = t.c{i})" for i in range(a))
    return f"(t.mask & s.mask) = s.mask AND t.mask <> s.mask AND {same}"


def _closed_cte(a: int = 4) -> tuple[str, str]:
    return "closed", f"SELECT * FROM sets s WHERE NOT EXISTS (SELECT 1 FROM sets t WHERE {_sub(a)} AND t.freq = s.freq)"


def _maximal_cte(least: str, a: int = 4, kind: str = "maximal") -> tuple[str, str]:
    if kind == "frequent":
        return "cand", f"SELECT * FROM sets s WHERE freq >= {least}"
    return "cand", f"SELECT * FROM sets s WHERE freq >= {least} AND NOT EXISTS (SELECT 1 FROM sets t WHERE {_sub(a)} AND t.freq >= {least})"


def _threshold_cte(k: float, reduce: str) -> tuple[str, str]:
    value = "min(freq)" if reduce == "min" else "CAST(ceil(avg(freq)) AS BIGINT)"
    return "threshold", f"SELECT greatest(2, {value}) AS s FROM (SELECT freq FROM closed ORDER BY freq DESC LIMIT (SELECT CAST(ceil({k} * count(*)) AS BIGINT) FROM rel))"


SCORES = {"area": "len * freq", "savings": "len * (freq - 1)", "rate": "round(len * (freq - 1) / ({a} * freq), 12)", "length": "len", "freq": "freq"}


def _greedy_ctes(a: int = 4, objective: str = "area") -> list[tuple[str, str]]:
    """From ``cand`` to ``chosen`` (the candidate's columns, its place, the tuples it covers), walking the order.

    A path of the prefix tree is ranked by the tuples on it, but covers all that hold its items.
    """
    cols = [f"c{i}" for i in range(a)]
    items = "list_filter([" + ", ".join(f"{{'p': {i}, 'v': c{i}}}" for i in range(a)) + "], lambda x: x.v IS NOT NULL)"
    join = " AND ".join(f"(r.c{i} = t.c{i} OR r.c{i} IS NULL)" for i in range(a))
    return [
        ("tup", f"SELECT row_number() OVER (ORDER BY {', '.join(cols)}) AS tid, * FROM rel"),
        ("ranked", f"SELECT *, row_number() OVER (ORDER BY {SCORES[objective].format(a=a)} DESC, {items}) AS rank FROM cand"),
        ("cov", f"SELECT r.rank, list(t.tid) AS tids FROM ranked r JOIN tup t ON {join} GROUP BY r.rank"),
        (
            "walk",
            """SELECT CAST(0 AS BIGINT) AS rank, CAST([] AS BIGINT[]) AS covered, false AS taken
               UNION ALL
               SELECT c.rank, CASE WHEN list_has_any(w.covered, c.tids) THEN w.covered ELSE list_concat(w.covered, c.tids) END, NOT list_has_any(w.covered, c.tids)
               FROM walk w JOIN cov c ON c.rank = w.rank + 1""",
        ),
        ("chosen", "SELECT r.* EXCLUDE (freq), len(c.tids) AS freq, c.tids FROM walk w JOIN ranked r USING (rank) JOIN cov c USING (rank) WHERE taken"),
        ("won", "SELECT rank, unnest(tids) AS tid FROM chosen"),
    ]


def _auto(k: float = K, reduce: str = "min", a: int = 4, sql: str | None = None, objective: str = "area", kind: str = "maximal") -> list[tuple[str, str]]:
    return [_rel_cte(sql), _sets_cte(a), _closed_cte(a), _threshold_cte(k, reduce), _maximal_cte("(SELECT s FROM threshold)", a, kind), *_greedy_ctes(a, objective)]


def _paths_ctes(a: int) -> list[tuple[str, str]]:
    """``cand`` from the prefixes of tuples with items by falling frequency."""
    each = " UNION ALL ".join(f"SELECT tid, {i} AS p, c{i} AS v FROM tup0" for i in range(a))
    back = ", ".join(f"max(CASE WHEN x.p = {i} THEN x.v END) AS c{i}" for i in range(a))
    return [
        ("tup0", f"SELECT row_number() OVER (ORDER BY {', '.join(f'c{i}' for i in range(a))}) AS tid, * FROM rel"),
        ("item", each),
        ("often", "SELECT p, v, count(*) AS f FROM item GROUP BY p, v"),
        ("ordered", "SELECT tid, list_sort(list({'f': -f, 'p': p, 'v': v})) AS s FROM item JOIN often USING (p, v) GROUP BY tid"),
        ("prefix", f"SELECT list_slice(s, 1, n) AS s, count(*) AS freq FROM ordered, (SELECT unnest(range(1, {a})) AS n) GROUP BY 1 HAVING count(*) >= 2"),
        ("item2", "SELECT row_number() OVER () AS id, s, freq FROM prefix"),
        ("cand", f"SELECT {back}, CAST(count(*) AS INT) AS len, any_value(freq) AS freq FROM (SELECT id, unnest(s) AS x, freq FROM item2) GROUP BY id"),
    ]


def _report_sql(a: int) -> str:
    return f"""SELECT CAST((SELECT count(*) FROM rel) AS BIGINT) AS tuples, CAST((SELECT count(*) FROM rel) * {a} AS BIGINT) AS cells, count(*) AS n_used,
      CAST(coalesce(sum(freq), 0) AS BIGINT) AS covered, CAST(coalesce(sum(len * (freq - 1)), 0) AS BIGINT) AS saved,
      round(coalesce(sum(freq), 0) / (SELECT count(*) FROM rel), 6) AS compressed_share, round(coalesce(sum(len * (freq - 1)), 0) / ((SELECT count(*) FROM rel) * {a}), 6) AS table_rate,
      round(coalesce(avg(len), 0), 6) AS mean_len, round(coalesce(avg(freq), 0), 6) AS mean_freq FROM chosen"""


def _live_where(alias: str = "") -> str:
    dot = f"{alias}." if alias else ""
    return " AND ".join(f"({dot}c{v} IS NULL OR {dot}c{v} NOT IN ({', '.join(map(str, c))}))" for v, c in REMOVED.items())


def _supported_sql(a: int = 4) -> str:
    return _with(_rel_cte(), ("ok", f"SELECT * FROM rel WHERE {_live_where()}")) + " " + " UNION ".join(f"SELECT {i} AS var, c{i} AS code FROM ok" for i in range(a))


# Queries --------------------------------------------------------------------------------------------------------------

QUERIES: dict[str, Query] = {}
ORACLE_SQL: dict[str, str] = {}


def query(oracle: str | None = None, name: str | None = None) -> Callable[[Query], Query]:
    def add(f: Query) -> Query:
        QUERIES[name or f.__name__] = f
        if oracle:
            ORACLE_SQL[name or f.__name__] = oracle
        return f

    return add


@query(_with(_rel_cte()) + " SELECT count(*) AS tuples, 4 AS arity, count(*) * 4 AS cells FROM rel")
def relation_cells(spark, sf):
    return metrics.cells(_rel(spark, sf))


@query(_with(_rel_cte()) + " " + " UNION ALL ".join(f"SELECT {i} AS var, count(DISTINCT c{i}) AS n FROM rel" for i in range(4)))
def domain_sizes(spark, sf):
    return _rel(spark, sf).domains().groupBy("var").agg(F.count("*").alias("n"))


@query(_with(_rel_cte()) + " " + " UNION ALL ".join(f"SELECT {i} AS p, c{i} AS v, count(*) AS freq FROM rel GROUP BY c{i} HAVING count(*) >= {S_FREQ}" for i in range(4)))
def item_frequency(spark, sf):
    return mining.frequent_items(_rel(spark, sf), S_FREQ)


_FREQUENT = _with(_rel_cte(), _sets_cte(4, S_FREQ)) + " SELECT c0, c1, c2, c3, len, freq FROM sets"


@query(_FREQUENT)
def frequent_itemsets_cube(spark, sf):
    return _flat(mining.frequent(_rel(spark, sf), S_FREQ))


@query(_FREQUENT)
def frequent_itemsets_levelwise(spark, sf):
    return _flat(mining.frequent_levelwise(_rel(spark, sf), S_FREQ))


@query(_FREQUENT)
def frequent_itemsets_growth(spark, sf):
    """The library's parallel growth of frequent patterns over set-valued transactions, recounted to the integer threshold."""
    rel = _rel(spark, sf)
    t = rel.df.select(F.transform(as_items(rel.scope), lambda x: x["p"].cast("bigint") * (1 << 32) + x["v"]).alias("items"))
    found = mining.frequent_growth(t, S_FREQ)
    back = F.array_sort(F.transform("items", lambda x: F.struct(F.shiftright(x, 32).cast("int").alias("p"), x.bitwiseAND(F.lit((1 << 32) - 1)).cast("int").alias("v"))))
    return _flat(found.select(back.alias("items"), F.size("items").alias("len"), "freq"))


_CLOSED = _with(_rel_cte(), _sets_cte(4, S_CLOSED), _closed_cte()) + " SELECT c0, c1, c2, c3, len, freq FROM closed"
_MAXIMAL = _with(_rel_cte(), _sets_cte(4, S_CLOSED), _maximal_cte(str(S_CLOSED))) + " SELECT c0, c1, c2, c3, len, freq FROM cand"


@query(_CLOSED)
def closed_itemsets(spark, sf):
    return _flat(mining.closed(mining.frequent(_rel(spark, sf), S_CLOSED)))


@query(_CLOSED)
def closed_itemsets_shards(spark, sf):
    return _flat(mining.closed_shards(_rel(spark, sf), S_CLOSED))


@query(_MAXIMAL)
def maximal_itemsets(spark, sf):
    return _flat(mining.maximal(mining.frequent(_rel(spark, sf), S_CLOSED)))


@query(_MAXIMAL)
def maximal_itemsets_shards(spark, sf):
    return _flat(mining.maximal_shards(_rel(spark, sf), S_CLOSED))


@query(_with(_rel_cte(), _sets_cte()) + " SELECT freq, count(*) AS n FROM (SELECT freq FROM sets ORDER BY freq DESC LIMIT 50) GROUP BY freq")
def topk_frequent(spark, sf):
    return mining.top(mining.frequent(_rel(spark, sf), 2), 50).groupBy("freq").agg(F.count("*").alias("n"))


@query(_with(_rel_cte(), _sets_cte(), _closed_cte()) + " SELECT freq, count(*) AS n FROM (SELECT freq FROM closed ORDER BY freq DESC LIMIT 50) GROUP BY freq")
def topk_closed(spark, sf):
    return mining.top(compression.candidates(_rel(spark, sf), 2, "closed"), 50).groupBy("freq").agg(F.count("*").alias("n"))


@query(_with(_rel_cte(), _sets_cte(), _closed_cte()) + " SELECT c0, c1, c2, c3, len, freq FROM closed QUALIFY rank() OVER (ORDER BY freq DESC) <= 50")
def topk_closed_ties(spark, sf):
    return _flat(mining.top(compression.candidates(_rel(spark, sf), 2, "closed"), 50, ties="include"))


@query(_with(_rel_cte(), _sets_cte()) + " SELECT c0, c1, c2, c3, len, freq FROM sets QUALIFY rank() OVER (ORDER BY len * freq DESC) <= 30")
def topk_area(spark, sf):
    return _flat(mining.top(mining.frequent(_rel(spark, sf), 2), 30, F.col("len") * F.col("freq"), "include"))


@query(
    _with(
        ("x", "SELECT DISTINCT l_orderkey AS o, p_brand AS b FROM lineitem JOIN part ON l_partkey = p_partkey"),
        ("one", "SELECT b AS items, count(*) AS freq FROM x GROUP BY b HAVING count(*) >= 5"),
        ("two", "SELECT s.b || ',' || t.b AS items, count(*) AS freq FROM x s JOIN x t ON s.o = t.o AND s.b < t.b GROUP BY 1 HAVING count(*) >= 5"),
    )
    + " SELECT items, freq FROM one UNION ALL SELECT items, freq FROM two"
)
def order_brands_frequent(spark, sf):
    """Set-valued transactions: brands bought together, up to pairs, as the SQL oracle's join has them."""
    return _brand_sets(spark, sf).where(F.size("items") <= 2).select(F.array_join("items", ",").alias("items"), "freq")


@query()
def order_brands_frequent_all(spark, sf):
    """Brands bought together, sets of every length."""
    return _brand_sets(spark, sf).select(F.array_join("items", ",").alias("items"), F.size("items").alias("len"), "freq")


def _brand_sets(spark: SparkSession, sf: str) -> DataFrame:
    line, part = spark.read.parquet(f"{sf}/lineitem.parquet"), spark.read.parquet(f"{sf}/part.parquet")
    t = line.join(part, line["l_partkey"] == part["p_partkey"]).groupBy("l_orderkey").agg(F.collect_set("p_brand").alias("items"))
    return mining.frequent_growth(t, 5)


@query(_with(_rel_cte(), _sets_cte(4, S_CLOSED), _maximal_cte(str(S_CLOSED)), *_greedy_ctes(), recursive=True) + " SELECT c0, c1, c2, c3, len, freq FROM chosen ORDER BY rank LIMIT 10")
def area_tiles(spark, sf):
    """Ten tiles: the disjoint itemsets of largest area in greedy order."""
    return _flat(compression.tiles(_rel(spark, sf), 10, S_CLOSED))


def _threshold_query(reduce: str) -> None:
    def f(spark, sf):
        rel = _rel(spark, sf)
        s = compression.support_threshold(rel, K, reduce)
        return spark.createDataFrame([(s,)], "threshold bigint")

    query(_with(_rel_cte(), _sets_cte(), _closed_cte(), _threshold_cte(K, reduce)) + " SELECT CAST(s AS BIGINT) AS threshold FROM threshold", f"threshold_{reduce}")(f)


for _r in ("min", "mean"):
    _threshold_query(_r)

GRID = [2, 3, 5, 9, 18, 27, 50, 100, 1000]


@query(_with(_rel_cte(), _sets_cte(), _closed_cte()) + " SELECT CAST(g AS INT) AS threshold, count(freq) AS n_sets FROM (SELECT unnest([" + ", ".join(map(str, GRID)) + "]) AS g) LEFT JOIN closed ON freq >= g GROUP BY g")
def threshold_curve(spark, sf):
    return mining.curve(compression.candidates(_rel(spark, sf), 2, "closed"), GRID)


SHARES = (0.2, 0.3, 0.4, 0.5, 0.6)


@query(
    _with(_rel_cte(), _sets_cte(), _closed_cte(), *[(f"t{i}_{r}", _threshold_cte(k, r)[1]) for i, k in enumerate(SHARES) for r in ("min", "mean")])
    + " "
    + " UNION ALL ".join(f"SELECT CAST({k} AS DOUBLE) AS k, '{r}' AS reduce, CAST(s AS BIGINT) AS threshold FROM t{i}_{r}" for i, k in enumerate(SHARES) for r in ("min", "mean"))
)
def threshold_sweep(spark, sf):
    rel = _rel(spark, sf)
    sets, n = staged(compression.candidates(rel, 2, "closed")), rel.df.count()
    return spark.createDataFrame([(k, r, mining.threshold(sets, mining.count_of(k, n), r)) for k in SHARES for r in ("min", "mean")], "k double, reduce string, threshold bigint")


@query(_with(_rel_cte(), _sets_cte(), _maximal_cte(str(S_CLOSED)), _greedy_ctes()[0], _greedy_ctes()[1]) + " SELECT rank AS place, len * freq AS area, c0, c1, c2, c3, len, freq FROM ranked")
def area_ranking(spark, sf):
    ranked = selection.rank(compression.candidates(_rel(spark, sf), S_CLOSED), 4)
    return _flat(ranked.select("items", "len", "freq", "rank", "score")).withColumn("area", F.col("len") * F.col("freq")).withColumn("place", F.row_number().over(Window.orderBy(F.desc("area"), as_items_of())).cast("bigint"))


def as_items_of():
    """Item list of the flat columns, for ordering."""
    return F.filter(F.array(*[F.when(F.col(c).isNotNull(), F.struct(F.lit(i).alias("p"), F.col(c).alias("v"))) for i, c in enumerate(COLS)]), lambda x: x.isNotNull())


def _compressed(spark, sf, **options):
    return compression.area_cover(_rel(spark, sf), K, options.pop("reduce", "min"), **options)


_HEADS = " SELECT c0, c1, c2, c3, len, freq FROM chosen"


@query(_with(*_auto(), recursive=True) + _HEADS)
def greedy_cover_drop(spark, sf):
    rel = _rel(spark, sf)
    ranked = selection.rank(compression.candidates(rel, compression.support_threshold(rel, K, "min")), 4)
    chosen, _ = selection.greedy(ranked, selection.cover(ranked, rel.numbered()))
    return _flat(ranked.join(chosen.select("rank").distinct(), "rank"))


@query()
def selection_steps(spark, sf):
    """What the choice costs: candidates, cover rows, and rounds (each two aggregations of the live covers)."""
    rel = _rel(spark, sf)
    ranked = selection.rank(compression.candidates(rel, S_CLOSED), 4)
    covers = staged(selection.cover(ranked, rel.numbered()), "covers")
    _, rounds = selection.greedy(ranked, covers)
    return spark.createDataFrame([(ranked.count(), covers.count(), rounds)], "candidates bigint, cover_rows bigint, rounds int")


@query()
def greedy_cover_shrink(spark, sf):
    return _flat(_compressed(spark, sf, overlap="shrink").heads)


@query(_with(*_auto(), recursive=True) + _HEADS)
def compressed_heads(spark, sf):
    return _flat(_compressed(spark, sf).heads)


@query(
    _with(*_auto(), recursive=True)
    + " SELECT "
    + ", ".join(f"CASE WHEN h.c{i} IS NULL THEN t.c{i} END AS c{i}" for i in range(4))
    + ", "
    + ", ".join(f"h.c{i} AS h{i}" for i in range(4))
    + " FROM won JOIN tup t USING (tid) JOIN chosen h USING (rank)"
)
def compressed_body(spark, sf):
    c = _compressed(spark, sf)
    heads = c.heads.select("entry", *[x.alias(f"h{i}") for i, x in enumerate(spread(F.col("items"), COLS))])
    return c.body.join(heads, "entry").select(*spread(F.col("items"), COLS), *[f"h{i}" for i in range(4)])


@query(_with(*_auto(0.6, "min", 3, W.products()), recursive=True) + " SELECT c0, c1, c2 FROM tup WHERE tid NOT IN (SELECT tid FROM won)")
def default_rows(spark, sf):
    c = compression.area_cover(_rel(spark, sf, W.products()), 0.6, "min")
    return c.default.select(*spread(F.col("items"), COLS[:3]))


@query(W.plain(W.dense()))
def roundtrip_rows(spark, sf):
    return _compressed(spark, sf).expand()


@query(_with(_rel_cte()) + f" SELECT * FROM rel WHERE {_live_where()}")
def compressed_where(spark, sf):
    """A selection answered on the compressed form."""
    return _compressed(spark, sf).where({v: (lambda x, codes=codes: ~x.isin(codes)) for v, codes in REMOVED.items()})


@query(_with(_rel_cte()) + " SELECT c1, c3 FROM rel WHERE c0 = 82 AND c2 = 5")
def single_entry(spark, sf):
    return compression.entry(_rel(spark, sf), {"c0": 82, "c2": 5})


@query(_with(*_auto(), recursive=True) + " SELECT c0, c1, c2, c3, freq * 4 AS before, len + (4 - len) * freq AS after, round(len * (freq - 1) / (4 * freq), 6) AS local_rate FROM chosen")
def entry_sizes(spark, sf):
    c = _compressed(spark, sf)
    sizes = metrics.entry_sizes(c.heads, 4).select("entry", "before", "after", F.round("local_rate", 6).alias("local_rate"))
    return c.heads.select("entry", *spread(F.col("items"), COLS)).join(sizes, "entry").drop("entry")


def _report_query(name: str, oracle: str | None, build: Callable) -> None:
    query(oracle, name)(lambda spark, sf: build(spark, sf).report())


for _k in (0.2, 0.4, 0.6):
    for _r in ("min", "mean"):
        _report_query(f"compression_report_k{int(_k * 100)}_{_r}", _with(*_auto(_k, _r), recursive=True) + " " + _report_sql(4), lambda spark, sf, k=_k, r=_r: compression.area_cover(_rel(spark, sf), k, r))
_report_query("compression_report_shrink", None, lambda spark, sf: _compressed(spark, sf, overlap="shrink"))
_report_query("products_report", _with(*_auto(0.4, "min", 3, W.products()), recursive=True) + " " + _report_sql(3), lambda spark, sf: compression.area_cover(_rel(spark, sf, W.products()), 0.4, "min"))
_report_query("labelled_report", _with(*_auto(0.4, "mean", 4, W.labelled()), recursive=True) + " " + _report_sql(4), lambda spark, sf: compression.area_cover(_rel(spark, sf, W.labelled()), 0.4, "mean"))

for _o in SCORES:
    _report_query(f"objective_{_o}", _with(*_auto(objective=_o), recursive=True) + " " + _report_sql(4), lambda spark, sf, o=_o: _compressed(spark, sf, objective=o))
_report_query("candidates_frequent", _with(*_auto(kind="frequent"), recursive=True) + " " + _report_sql(4), lambda spark, sf: _compressed(spark, sf, kind="frequent"))
_report_query("threshold_fixed_2", _with(_rel_cte(), _sets_cte(), _maximal_cte("2"), *_greedy_ctes(), recursive=True) + " " + _report_sql(4), lambda spark, sf: _compressed(spark, sf, s_min=2))

for _c in ("paths", "all"):
    for _o, _n in (("savings", "savings_slice"), ("rate", "rate_tree")):
        _cand = _paths_ctes(4) if _c == "paths" else [_sets_cte(), _maximal_cte("2", 4, "frequent")]
        _report_query(f"{_n}_{_c}_report", _with(_rel_cte(), *_cand, *_greedy_ctes(4, _o), recursive=True) + " " + _report_sql(4), lambda spark, sf, c=_c, o=_o: compression.slices(_rel(spark, sf), 2, c, o))
_report_query("microstructure_report", None, lambda spark, sf: compression.microstructure(_rel(spark, sf)))


_PRODUCTS = [
    _rel_cte(),
    ("p3", "SELECT c0, c1, c2, list_sort(list(c3)) AS s3 FROM rel GROUP BY c0, c1, c2"),
    ("p2", "SELECT c0, c1, s3, list_sort(list(c2)) AS s2 FROM p3 GROUP BY c0, c1, s3"),
    ("p1", "SELECT c0, s2, s3, list_sort(list(c1)) AS s1 FROM p2 GROUP BY c0, s2, s3"),
    ("p0", "SELECT s1, s2, s3, list_sort(list(c0)) AS s0 FROM p1 GROUP BY s1, s2, s3"),
]


@query(
    _with(*_PRODUCTS)
    + " SELECT " + ", ".join(f"array_to_string(s{i}, ',') AS c{i}" for i in range(4)) + " FROM p0"
)
def cartesian_rows(spark, sf):
    return compression.cartesian(_rel(spark, sf)).select(*[F.array_join(F.transform(c, lambda v: v.cast("string")), ",").alias(c) for c in COLS])


def _wildcard_sql() -> str:
    cols, steps, before = [f"c{i}" for i in range(4)], [_rel_cte(), ("w4", 'SELECT *, 0 AS "any" FROM rel')], "w4"
    for i in (3, 2, 1, 0):
        rest = ", ".join(c for c in cols if c != f"c{i}")
        counted = f'SELECT *, count(*) OVER (PARTITION BY {rest}, "any") = (SELECT count(DISTINCT c{i}) FROM rel) AS whole FROM {before}'
        out = ", ".join(c if c != f"c{i}" else f"CASE WHEN whole THEN NULL ELSE c{i} END AS c{i}" for c in cols)
        steps.append((f"w{i}", f'SELECT DISTINCT {out}, "any" + CASE WHEN whole THEN {1 << i} ELSE 0 END AS "any" FROM ({counted})'))
        before = f"w{i}"
    return _with(*steps) + ' SELECT c0, c1, c2, c3, CAST("any" AS BIGINT) AS "any" FROM w0'


@query(_wildcard_sql())
def wildcard_rows(spark, sf):
    return compression.wildcard(_rel(spark, sf))


@query(
    _with(*_PRODUCTS)
    + " SELECT " + ", ".join(f"list_min(s{i}) AS c{i}_lo, list_max(s{i}) AS c{i}_hi, CASE WHEN len(s{i}) = list_max(s{i}) - list_min(s{i}) + 1 THEN '' ELSE array_to_string(s{i}, ',') END AS c{i}_set" for i in range(4)) + " FROM p0"
)
def restricted_rows(spark, sf):
    """Ranges, and the set where a range has gaps."""
    d = compression.restricted(_rel(spark, sf))
    sets = [F.when(F.col(f"{c}.dense"), F.lit("")).otherwise(F.array_join(F.transform(f"{c}.set", lambda v: v.cast("string")), ",")).alias(f"{c}_set") for c in COLS]
    return d.select(*[F.col(f"{c}.lo").alias(f"{c}_lo") for c in COLS], *[F.col(f"{c}.hi").alias(f"{c}_hi") for c in COLS], *sets)


@query(_with(*_auto(), recursive=True) + " SELECT c0, c1, c2, c3, len, CAST(len(tids) AS INT) AS rows FROM chosen UNION ALL SELECT NULL, NULL, NULL, NULL, 0, 1 FROM tup WHERE tid NOT IN (SELECT tid FROM won)")
def segmented_rows(spark, sf):
    """Heads with the rows nested in each; a row that no head has stands alone."""
    d = compression.segmented(_compressed(spark, sf), 1 << 30)
    return d.select(*spread(F.col("items"), COLS), F.size("items").alias("len"), F.size("rows").alias("rows"))


def _smart_sql() -> str:
    op = "CASE WHEN {0} = {1} THEN '=' WHEN {0} < {1} THEN '<' ELSE '>' END"
    groups = []
    for x in range(4):
        for y in range(x + 1, 4):
            rest = [f"c{i}" for i in range(4) if i not in (x, y)]
            whole = f"SELECT {op.format('a', 'b')} AS op, count(*) AS n FROM (SELECT DISTINCT c{x} AS a FROM rel), (SELECT DISTINCT c{y} AS b FROM rel) GROUP BY 1"
            held = f"SELECT {', '.join(rest)}, {op.format(f'c{x}', f'c{y}')} AS op, count(*) AS n FROM rel GROUP BY ALL"
            groups.append(f"SELECT {x} AS x, {y} AS y, h.op, {', '.join(f'h.c{i}' if f'c{i}' in rest else f'NULL AS c{i}' for i in range(4))}, h.n AS freq FROM ({held}) h JOIN ({whole}) w ON h.op = w.op AND h.n = w.n WHERE h.n >= 2")
    items = "list_filter([" + ", ".join(f"{{'p': {i}, 'v': c{i}}}" for i in range(4)) + "], lambda z: z.v IS NOT NULL)"
    fits = " AND ".join(f"(g.c{i} IS NULL OR g.c{i} = t.c{i})" for i in range(4))
    at = {v: "CASE " + " ".join(f"WHEN g.{v} = {i} THEN t.c{i}" for i in range(4)) + " END" for v in "xy"}
    return _with(
        _rel_cte(),
        ("tup", "SELECT row_number() OVER (ORDER BY c0, c1, c2, c3) AS tid, * FROM rel"),
        ("cand", " UNION ALL ".join(groups)),
        ("ranked", f"SELECT *, row_number() OVER (ORDER BY freq DESC, x, y, op, {items}) AS rank FROM cand"),
        ("cov", f"SELECT g.rank, list(t.tid) AS tids FROM ranked g JOIN tup t ON {fits} AND g.op = {op.format(at['x'], at['y'])} GROUP BY g.rank"),
        _greedy_ctes()[3],
        recursive=True,
    ) + " SELECT r.x, r.y, r.op, r.c0, r.c1, r.c2, r.c3, r.freq FROM walk w JOIN ranked r USING (rank) WHERE taken"


@query(_smart_sql())
def smart_rows(spark, sf):
    """Rows with a comparison of two columns in place of the pairs of values for which it holds."""
    return compression.smart(_rel(spark, sf))[0].select("x", "y", "op", *spread(F.col("items"), COLS), "freq")


_SUFFIX = [
    _rel_cte(),
    ("n3", "SELECT c0, c1, c2, list_sort(list(DISTINCT c3)) AS s FROM rel GROUP BY c0, c1, c2"),
    ("n2", "SELECT c0, c1, list_sort(list(DISTINCT {'k': c2, 's': s})) AS s FROM n3 GROUP BY c0, c1"),
    ("n1", "SELECT c0, list_sort(list(DISTINCT {'k': c1, 's': s})) AS s FROM n2 GROUP BY c0"),
]


@query(
    _with(*_SUFFIX)
    + " SELECT 0 AS level, CAST(1 AS BIGINT) AS nodes, count(*) AS edges FROM n1 UNION ALL SELECT 1, count(*), CAST(sum(len(s)) AS BIGINT) FROM (SELECT DISTINCT s FROM n1)"
    + " UNION ALL SELECT 2, count(*), CAST(sum(len(s)) AS BIGINT) FROM (SELECT DISTINCT s FROM n2) UNION ALL SELECT 3, count(*), CAST(sum(len(s)) AS BIGINT) FROM (SELECT DISTINCT s FROM n3)"
)
def diagram_levels(spark, sf):
    e = compression.diagram(_rel(spark, sf))
    return e.groupBy("level").agg(F.countDistinct("node").alias("nodes"), F.count("*").alias("edges"))


# All words of the automaton are of one length, so states of two levels are never equal.
@query(_with(*_SUFFIX) + " SELECT CAST(1 + (SELECT count(*) FROM (SELECT DISTINCT s FROM n1)) + (SELECT count(*) FROM (SELECT DISTINCT s FROM n2)) + (SELECT count(*) FROM (SELECT DISTINCT s FROM n3)) AS BIGINT) AS states")
def automaton_states(spark, sf):
    e = compression.diagram(_rel(spark, sf), automaton=True)
    return e.select("node").distinct().agg(F.count("*").alias("states"))


@query(_with(_rel_cte()) + " " + " UNION ALL ".join(f"SELECT {i} AS var, c{i} AS code, count(*) AS n FROM rel GROUP BY c{i}" for i in range(4)))
def bitset_cardinality(spark, sf):
    return compression.bitset(compression.dense(_rel(spark, sf))).groupBy("var", "code").agg(F.sum(F.bitmap_count("bits")).alias("n"))


# Filters: the same removals, the same result.


def _setting(spark, sf):
    rel = _rel(spark, sf)
    domains = filters.restrict(rel.domains(), REMOVED)
    gone = spark.createDataFrame([(v, c) for v, codes in REMOVED.items() for c in codes], "var int, code int")
    return rel, domains, gone


def _filter_query(name: str, f: Callable) -> None:
    query(_supported_sql(), f"filter_{name}")(lambda spark, sf: f(*_setting(spark, sf)).select("var", "code"))


_filter_query("scan", lambda r, d, g: filters.scan(r.numbered(), d, 4))
_filter_query("settled", lambda r, d, g: filters.settled(r.numbered(), d, 4, list(REMOVED)))
_filter_query("dual", lambda r, d, g: filters.dual(r.numbered(), g))
_filter_query("counters", lambda r, d, g: filters.counters(r.numbered(), g))
_filter_query("counters_reset", lambda r, d, g: filters.counters(r.numbered(), g, "auto"))
_filter_query("diagram", lambda r, d, g: filters.diagram(compression.diagram(r), 4, d))
_filter_query("bitset_lists", lambda r, d, g: filters.bitset(compression.bitset(compression.dense(r)), d, 4, None, "lists"))
_filter_query("bitset_current", lambda r, d, g: filters.bitset(compression.bitset(compression.dense(r)), d, 4, list(REMOVED), "current"))
_filter_query("cartesian", lambda r, d, g: filters.cartesian(compression.cartesian(r), r.scope, d))
_filter_query("wildcard", lambda r, d, g: filters.wildcard(compression.wildcard(r), r.scope, d))
_filter_query("restricted", lambda r, d, g: filters.restricted(compression.restricted(r), r.scope, d))
_filter_query("smart", lambda r, d, g: filters.smart(*compression.smart(r), d, 4))
_filter_query("bitset_short", lambda r, d, g: filters.bitset_rows(compression.wildcard(r), r.scope, d))
_filter_query("bitset_products", lambda r, d, g: filters.bitset_rows(compression.cartesian(r), r.scope, d))
_filter_query("entries", lambda r, d, g: filters.entries(compression.area_cover(r, K, "min"), d)[0])
_filter_query("entries_on_slices", lambda r, d, g: filters.entries(compression.savings_slice(r), d)[0])


@query(_supported_sql(), "filter_residues")
def _residues(spark, sf):
    rel, domains, _ = _setting(spark, sf)
    tuples = rel.numbered()
    return filters.residues(tuples, domains, 4, filters.residues_of(tuples))


@query("WITH rel AS (SELECT DISTINCT n_nationkey AS c0, n_regionkey AS c1 FROM nation), pair AS (SELECT a.c0 AS v0, a.c1 AS v1, b.c0 AS v2 FROM rel a, rel b) SELECT v0, v1, v2 FROM pair p WHERE NOT EXISTS (SELECT 1 FROM rel r WHERE r.c0 = p.v2 AND r.c1 = p.v1)")
def forbidden_solutions(spark, sf):
    """Two nations and a region: the first lies in it, the second must not (a table of forbidden tuples)."""
    inst = _nations(spark, sf)
    return inst.solve_by_join(spark)


@query("SELECT DISTINCT 0 AS var, n_nationkey AS code FROM nation UNION SELECT 1, n_regionkey FROM nation UNION SELECT 2, n_nationkey FROM nation")
def forbidden_propagate(spark, sf):
    """Every nation is outside some region, so all values have a support."""
    return _nations(spark, sf).propagate(spark)


def _nations(spark: SparkSession, sf: str) -> Instance:
    rel = W.relation(spark, sf, W.pairs()["nation_region"], "nation_region")
    nations, regions = (sorted(r[0] for r in rel.df.select(c).distinct().collect()) for c in rel.scope)  # finite domains
    other = Relation(rel.df, rel.scope, "other_region", sign=False)
    return Instance({0: nations, 1: regions, 2: nations}, [Constraint(rel, [0, 1]), Constraint(other, [2, 1])])


# Filters with kept state: removals at two depths, and back to the first.

REMOVED_DEEPER = {1: [70], 2: [4, 5, 6, 7, 8, 9, 10]}


def _chain_sql() -> str:
    gone = " AND ".join(f"c{v} NOT IN ({', '.join(map(str, c))})" for v, c in REMOVED_DEEPER.items())
    steps = [("first", _live_where()), ("deeper", f"{_live_where()} AND {gone}"), ("back", _live_where())]
    return _with(_rel_cte()) + " " + " UNION ".join(f"SELECT '{n}' AS call, {i} AS var, c{i} AS code FROM rel WHERE {w}" for n, w in steps for i in range(4))


def _values(spark: SparkSession, codes: dict[int, list[int]]) -> DataFrame:
    return spark.createDataFrame([(v, c) for v, listed in codes.items() for c in listed], "var int, code int")


def _chain_query(method: str) -> None:
    def f(spark, sf):
        state = stateful.kept(_rel(spark, sf), method)
        first = state.remove(_values(spark, REMOVED), 1)
        deeper = state.remove(_values(spark, REMOVED_DEEPER), 2)
        state.back(1)
        calls = {"first": first, "deeper": deeper, "back": state.supported()}
        return reduce(DataFrame.unionByName, [d.select(F.lit(n).alias("call"), "var", "code") for n, d in calls.items()])

    query(_chain_sql(), f"filter_chain_{method}")(f)


for _m in ("lists", "counters", "counters_reset", "bits", "diagram", "entries", "entries_slices"):
    _chain_query(_m)


@query(
    _with(*_auto(), recursive=True)
    + f" SELECT h.c0, h.c1, h.c2, h.c3, CAST(count(*) FILTER (WHERE {_live_where('t')}) AS BIGINT) AS live, count(*) AS rows FROM won JOIN tup t USING (tid) JOIN chosen h USING (rank) GROUP BY ALL"
)
def entry_liveness(spark, sf):
    rel, domains, _ = _setting(spark, sf)
    c = compression.area_cover(rel, K, "min")
    return filters.entries(c, domains)[1].join(c.heads.select("entry", *spread(F.col("items"), COLS)), "entry").drop("entry")


@query(
    _with(_rel_cte()) + " SELECT depth, CAST(live AS BIGINT) AS live FROM (SELECT 1 AS depth, count(*) FILTER (WHERE c0 <> 65) AS live FROM rel UNION ALL "
    "SELECT 2, count(*) FILTER (WHERE c0 <> 65 AND c2 > 3) FROM rel UNION ALL SELECT 0, count(*) FROM rel)"
)
def restore_depths(spark, sf):
    """Live rows after two filter calls, and after going back to each depth."""
    rel = _rel(spark, sf)
    rows = rel.numbered().withColumn("dead_at", F.lit(None).cast("int"))
    rows = filters.mark(rows, filters.restrict(rel.domains(), {0: [65]}), 4, 1)
    rows = staged(filters.mark(rows, filters.restrict(rel.domains(), {0: [65], 2: [0, 1, 2, 3]}), 4, 2))
    back = [filters.restore(rows, depth).agg(F.count_if(F.col("dead_at").isNull()).alias("live")).select(F.lit(depth).alias("depth"), "live") for depth in (0, 1, 2)]
    return back[0].unionByName(back[1]).unionByName(back[2])


@query(_with(*_auto(), ("ok", f"SELECT * FROM chosen WHERE {_live_where()}"), recursive=True) + " SELECT CAST((SELECT count(*) FROM rel) * 4 AS BIGINT) AS flat_cells, CAST((SELECT sum(len) FROM chosen) + (SELECT sum((4 - len) * freq) FROM ok) + ((SELECT count(*) FROM rel) - (SELECT sum(freq) FROM chosen)) * 4 AS BIGINT) AS entry_cells")
def filter_work(spark, sf):
    rel, domains, _ = _setting(spark, sf)
    return filters.work(compression.area_cover(rel, K, "min"), domains)


@query(_with(*_auto(), recursive=True) + " SELECT CAST(sum(saved) AS BIGINT) AS saved FROM (SELECT len * (freq - 1) AS saved FROM chosen)")
def cells_saved(spark, sf):
    return _compressed(spark, sf).heads.agg(F.sum(saving(F.col("len"), F.col("freq"))).alias("saved"))


_EVENTS = "SELECT ts, ascii(event_type) AS c0, CAST(hour(ts) AS INT) AS c1 FROM events"


@query(
    f"WITH e AS ({_EVENTS}), x AS (SELECT date_trunc('day', ts) AS start, 0 AS p, c0 AS v FROM e UNION ALL SELECT date_trunc('day', ts), 1, c1 FROM e)"
    " SELECT CAST(epoch(start) AS BIGINT) AS start, p, v, count(*) AS freq FROM x GROUP BY ALL"
)
def events_window_items(spark, sf):
    """Item frequencies of events by day."""
    rows = streams.tuples(spark.read.parquet(f"{sf}/events.parquet"))
    return streams.item_counts(rows, ["c0", "c1"], "1 day").select(F.unix_timestamp("start").alias("start"), "p", "v", "freq")


@query(
    _with(("rel", "SELECT DISTINCT ascii(event_type) AS c0, CAST(hour(ts) AS INT) AS c1 FROM events WHERE ts < (SELECT min(ts) + INTERVAL 1 DAY FROM events)"), *_auto(0.4, "min", 2)[1:], recursive=True)
    + f", e AS ({_EVENTS}), put AS (SELECT e.*, EXISTS (SELECT 1 FROM chosen h WHERE (h.c0 IS NULL OR h.c0 = e.c0) AND (h.c1 IS NULL OR h.c1 = e.c1)) AS fits FROM e)"
    " SELECT count(*) AS n, count(*) FILTER (WHERE NOT fits) AS n_default, round(count(*) FILTER (WHERE NOT fits) / greatest(count(*), 1), 6) AS share FROM put"
)
def events_assignment(spark, sf):
    """All events put to the entries of the (type, hour) relation of the first day, and the share left to its default table."""
    rows = streams.tuples(spark.read.parquet(f"{sf}/events.parquet"))
    day = rows.agg((F.min("ts") + F.expr("INTERVAL 1 DAY")).alias("_end"))
    first = rows.join(day, F.col("ts") < F.col("_end"), "left_semi")
    return streams.default_share(streams.assign(rows, compression.area_cover(Relation.of(first, ["c0", "c1"]), 0.4, "min")))


# The seven-column relations, and the parameters' directions. The walk of the SQL oracle is slow: it has 1,000 tuples of one slice.

_report_query("modular_report", _with(*_auto(0.2, "mean", 7, W.modular(1000, 20)), recursive=True) + " " + _report_sql(7), lambda spark, sf: compression.area_cover(_rel(spark, sf, W.modular(1000, 20)), 0.2, "mean"))


MODULAR_SLICES, MODULAR_SIZES = 20, (2500, 5000, 7500, 10000)


@query()
def modular_workloads_report(spark, sf):
    """Every slice of the seven-column relations at the workloads' sizes (W3-W6): one row of measures for each slice and size.

    All slices are compressed in one job, a task each.
    """
    parts = []
    for size in MODULAR_SIZES:
        rows = W.rows(spark, sf, W.modular_slices(size, MODULAR_SLICES))
        parts.append(rows.select(F.concat_ws("_", F.lit(size), "which").alias("rel_id"), F.array(*[F.col(f"c{i}").cast("int") for i in range(7)]).alias("vals")))
    found = experiments.compressed(reduce(DataFrame.unionByName, parts), {"area_cover": (lambda rows: experiments.varied(rows, 0.2, "mean"), False)})
    at = F.split("rel_id", "_")
    columns = ["tuples", "cells", "n_used", "covered", "saved", "compressed_share", "table_rate", "mean_len", "mean_freq"]
    return found.select(at[1].cast("int").alias("slice"), at[0].cast("int").alias("size"), *columns)


def _words_sql() -> str:
    words, out = W.plain(W.words(4, "en", True)), []
    forms = {f"area_cover_{r}": [("rel", words), *_auto(0.4, r)[1:]] for r in ("min", "mean")}
    for o in ("savings", "rate"):
        for c in ("paths", "all"):
            forms[f"{o}_{c}"] = [("rel", words), *(_paths_ctes(4) if c == "paths" else [_sets_cte(), _maximal_cte("2", 4, "frequent")]), *_greedy_ctes(4, o)]
    for name, ctes in forms.items():
        report = _report_sql(4).replace(" FROM chosen", ", (SELECT count(*) FROM cand) AS n_mined FROM chosen")
        out.append(f"SELECT *, '{name}' AS method FROM ({_with(*ctes, recursive=True)} {report})")
    return " UNION ALL BY NAME ".join(out)


@query(_words_sql())
def words_compared(spark, sf):
    """Area-cover against the four readings of the itemset baselines on four-letter words: one row of measures each."""
    rel = _rel(spark, sf, W.words(4))
    forms = {"area_cover_min": compression.area_cover(rel, 0.4, "min"), "area_cover_mean": compression.area_cover(rel, 0.4, "mean")}
    forms |= {f"{o}_{c}": compression.slices(rel, 2, c, o) for o in ("savings", "rate") for c in ("paths", "all")}
    out = [c.report().withColumns({"method": F.lit(m), "n_mined": F.lit(c.n_mined).cast("bigint")}) for m, c in forms.items()]
    return reduce(DataFrame.unionByName, out)


@query()
def booleans_report(spark, sf):
    """Eighteen two-valued columns at the automatic threshold: the shard engine, as a cube would be too wide."""
    return compression.area_cover(_rel(spark, sf, W.booleans_large()), 0.2, "mean").report()


QUERIES |= solving.QUERIES | experiments.QUERIES
ORACLE_SQL |= solving.ORACLE_SQL | experiments.ORACLE_SQL
