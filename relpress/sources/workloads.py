"""The experiments' relations on the given tables, as SQL that both engines read ({table} names a source)."""

from __future__ import annotations

import re

from pyspark.sql import DataFrame, SparkSession

from ..model import Relation

_LINE = [
    "l_quantity > 25", "CAST(l_quantity AS INT) % 2 = 0", "l_discount > 0.05", "CAST(round(l_discount * 100) AS INT) % 2 = 0", "l_tax > 0.04", "CAST(round(l_tax * 100) AS INT) % 2 = 0",
    "l_returnflag = 'A'", "l_returnflag = 'R'", "l_linestatus = 'O'", "month(l_shipdate) > 6", "month(l_shipdate) % 2 = 0", "day(l_shipdate) > 15", "year(l_shipdate) % 2 = 0",
    "l_linenumber > 3", "l_linenumber % 2 = 0", "l_extendedprice > 30000", "l_partkey % 2 = 0", "l_suppkey % 2 = 0",
]
_ORDER = [
    "o_orderstatus = 'F'", "o_orderstatus = 'O'", "o_orderpriority < '2'", "o_orderpriority < '3'", "o_orderpriority < '4'", "o_orderpriority < '5'", "month(o_orderdate) > 6", "month(o_orderdate) % 2 = 0",
    "day(o_orderdate) > 15", "year(o_orderdate) % 2 = 0", "o_totalprice > 150000", "o_totalprice > 250000", "o_custkey % 2 = 0", "o_orderkey % 2 = 0", "year(o_orderdate) > 1996",
]


def _select(expressions: list[str], source: str, cast: bool = True) -> str:
    body = ", ".join(f"{f'CAST({e} AS INT)' if cast else e} AS c{i}" for i, e in enumerate(expressions))
    return f"SELECT DISTINCT {body} FROM {source}"


def dense() -> str:
    """Nearly the full product of flag, status, discount and tax (W12)."""
    return _select(["ascii(l_returnflag)", "ascii(l_linestatus)", "round(l_discount * 100)", "round(l_tax * 100)"], "{lineitem}")


def dense_quantity() -> str:
    return _select(["ascii(l_returnflag)", "ascii(l_linestatus)", "round(l_discount * 100)", "round(l_tax * 100)", "l_quantity"], "{lineitem}")


def booleans_large(size: int | None = None) -> str:
    """18 two-valued columns (W1), cut to ``size`` tuples by an arithmetic scramble."""
    inner = _select(_LINE, "{lineitem}")
    if size is None:
        return inner
    mix = " + ".join(f"c{i} * {(4099 * (i + 1) ** 2) % 65521}" for i in range(len(_LINE)))
    return f"SELECT * FROM ({inner}) AS t ORDER BY ({mix}) % 64997, {', '.join(f'c{i}' for i in range(len(_LINE)))} LIMIT {size}"


def booleans_small() -> str:
    """15 two-valued columns (W2)."""
    return _select(_ORDER, "{orders}")


def modular(size: int = 2500, slices: int = 20, which: int = 0) -> str:
    """Seven columns of eight values, one slice of orders cut to ``size`` by an arithmetic scramble (W3-W6)."""
    parts = ["l_orderkey", "l_partkey", "l_suppkey", "l_linenumber", "CAST(l_quantity AS INT)", "CAST(round(l_discount * 100) AS INT)", "CAST(round(l_tax * 100) AS INT)"]
    inner = _select([f"({p}) % 8" for p in parts], f"{{lineitem}} WHERE CAST(floor(l_orderkey / 8) AS BIGINT) % {slices} = {which}")
    mix = "(4099 * c0 + 2053 * c1 + 1031 * c2 + 521 * c3 + 257 * c4 + 131 * c5 + 67 * c6) % 997"
    return f"SELECT * FROM ({inner}) AS t ORDER BY {mix}, c0, c1, c2, c3, c4, c5, c6 LIMIT {size}"


def modular_slices(size: int, slices: int) -> str:
    """All slices of the modular columns, each cut to ``size`` as ``modular`` cuts one: which, c0 to c6."""
    parts = ["l_orderkey", "l_partkey", "l_suppkey", "l_linenumber", "CAST(l_quantity AS INT)", "CAST(round(l_discount * 100) AS INT)", "CAST(round(l_tax * 100) AS INT)"]
    cols = ", ".join(f"c{i}" for i in range(7))
    inner = f"SELECT DISTINCT CAST(floor(l_orderkey / 8) AS BIGINT) % {slices} AS which, {', '.join(f'CAST(({p}) % 8 AS INT) AS c{i}' for i, p in enumerate(parts))} FROM {{lineitem}}"
    mix = "(4099 * c0 + 2053 * c1 + 1031 * c2 + 521 * c3 + 257 * c4 + 131 * c5 + 67 * c6) % 997"
    return f"SELECT which, {cols} FROM (SELECT *, row_number() OVER (PARTITION BY which ORDER BY {mix}, {cols}) AS place FROM ({inner}) AS t) AS u WHERE place <= {size}"


def words(length: int, lang: str | None = "en", duckdb: bool = False) -> str:
    """Words of one length, a column a letter (W7 with one language, W8 with all)."""
    where = f"WHERE lang = '{lang}'" if lang else ""
    found = "unnest(regexp_extract_all(lower(text), '[a-z]+'))" if duckdb else "explode(regexp_extract_all(lower(text), '[a-z]+', 0))"
    inner = f"SELECT DISTINCT w FROM (SELECT {found} AS w FROM {{documents}} {where}) AS x WHERE length(w) = {length}"
    return f"SELECT {', '.join(f'ascii(substr(w, {i + 1}, 1)) - 97 AS c{i}' for i in range(length))} FROM ({inner}) AS y"


def products() -> str:
    """Brand, type and size of parts (W9a), by the number in the brand and the rank of the type's first letters."""
    return "SELECT DISTINCT CAST(substr(p_brand, 7) AS INT) AS c0, ascii(p_type) * 256 + ascii(substr(p_type, 2, 1)) AS c1, p_size AS c2 FROM {part}"


def configurator() -> str:
    """Ten attributes of an order line over five tables (W9b)."""
    return """SELECT DISTINCT CAST(substr(p_brand, 7) AS INT) AS c0, ascii(p_type) * 256 + ascii(substr(p_type, 2, 1)) AS c1, p_size AS c2, s_nationkey AS c3,
      ascii(c_mktsegment) AS c4, CAST(substr(o_orderpriority, 1, 1) AS INT) AS c5, ascii(o_orderstatus) AS c6, ascii(l_returnflag) AS c7, ascii(l_linestatus) AS c8, c_nationkey AS c9
      FROM {lineitem} JOIN {orders} ON l_orderkey = o_orderkey JOIN {part} ON l_partkey = p_partkey JOIN {supplier} ON l_suppkey = s_suppkey JOIN {customer} ON o_custkey = c_custkey"""


def configurator_parts() -> list[tuple[str, int, str]]:
    """The configurator's relations (name, columns, SQL) in small codes from 0: letters count from A."""
    letter = "ascii({}) - 65"
    joined = "{lineitem} JOIN {orders} ON l_orderkey = o_orderkey JOIN {part} ON l_partkey = p_partkey JOIN {supplier} ON l_suppkey = s_suppkey JOIN {customer} ON o_custkey = c_custkey"
    brand, kind, size = "CAST(substr(p_brand, 7) AS INT)", letter.format("p_type"), "p_size"
    status, flag, line, segment = letter.format("o_orderstatus"), letter.format("l_returnflag"), letter.format("l_linestatus"), letter.format("c_mktsegment")
    priority = "CAST(substr(o_orderpriority, 1, 1) AS INT)"
    ten = _select([brand, kind, size, "s_nationkey", segment, priority, status, flag, line, "c_nationkey"], joined)
    cols = [f"c{i}" for i in range(10)]
    mix = " + ".join(f"{c} * {p}" for c, p in zip(cols, (4099, 2053, 1031, 521, 257, 131, 67, 37, 17, 7)))
    return [
        ("parts", 10, f"SELECT * FROM ({ten}) AS t ORDER BY ({mix}) % 9973, {', '.join(cols)} LIMIT 48721"),
        ("product", 3, _select([brand, kind, size], "{part}")),
        ("nation_region", 2, _select(["n_nationkey", "n_regionkey"], "{nation}")),
        ("nation_segment", 2, _select(["c_nationkey", segment], "{customer}")),
        ("status_priority", 2, _select([status, priority], "{orders}")),
        ("flag_status", 2, _select([flag, line], "{lineitem}")),
    ]


def labelled() -> str:
    """Language, source number, quality and toxicity of documents, -1 where there is no label (W9c)."""
    return """SELECT DISTINCT ascii(lang) * 256 + ascii(substr(lang, 2, 1)) AS c0, CAST(substr(source, 4) AS INT) AS c1, coalesce(quality, -1) AS c2, coalesce(toxic, -1) AS c3
      FROM {documents} AS d LEFT JOIN {labels} AS l ON d.doc_id = l.doc_id"""


def pairs() -> dict[str, str]:
    """Small binary relations of the configurator (W9d)."""
    return {
        "nation_region": "SELECT DISTINCT n_nationkey AS c0, n_regionkey AS c1 FROM {nation}",
        "nation_segment": "SELECT DISTINCT c_nationkey AS c0, ascii(c_mktsegment) AS c1 FROM {customer}",
        "status_priority": "SELECT DISTINCT ascii(o_orderstatus) AS c0, CAST(substr(o_orderpriority, 1, 1) AS INT) AS c1 FROM {orders}",
        "flag_status": "SELECT DISTINCT ascii(l_returnflag) AS c0, ascii(l_linestatus) AS c1 FROM {lineitem}",
        "type_hour": "SELECT DISTINCT ascii(event_type) AS c0, hour(ts) AS c1 FROM {events}",
    }


def plain(sql: str) -> str:
    """The SQL with table names in place."""
    return re.sub(r"\{(\w+)\}", r"\1", sql)


def rows(spark: SparkSession, sf_dir: str, sql: str) -> DataFrame:
    tables: dict[str, DataFrame] = {t: spark.read.parquet(f"{sf_dir}/{t}.parquet") for t in sorted(set(re.findall(r"\{(\w+)\}", sql)))}
    return spark.sql(sql, **tables)


def relation(spark: SparkSession, sf_dir: str, sql: str, name: str = "relation") -> Relation:
    """Run a workload's SQL over the Parquet tables it names."""
    df = rows(spark, sf_dir, sql)
    return Relation(df.select(*[df[c].cast("int").alias(c) for c in df.columns]), df.columns, name)
