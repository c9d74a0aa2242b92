"""Relations that arrive as a stream: item counts in windows, and assignment of new tuples to the entries of a compressed form.

Every function takes a batch or a streaming DataFrame of tuples with an event time; the batch form is what the streaming
one has given once all rows are in and none was late.
"""

from __future__ import annotations

from functools import reduce

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F
from pyspark.sql.streaming import StreamingQuery

from ..functions.itemsets import as_items, mask_of, value_at
from ..model import CompressedRelation


def read(spark: SparkSession, path: str, schema: str) -> DataFrame:
    """A stream of Parquet files."""
    return spark.readStream.schema(schema).parquet(path)


def tuples(events: DataFrame) -> DataFrame:
    """(ts, c0, c1): type and hour of events, as codes."""
    return events.select("ts", F.ascii("event_type").alias("c0"), F.hour("ts").alias("c1"))


def item_counts(rows: DataFrame, scope: list[str], width: str = "1 hour", slide: str | None = None, late: str | None = None) -> DataFrame:
    """(start, p, v, freq): item frequencies in tumbling or sliding windows; with ``late``, a watermark bounds the state."""
    if late is not None:
        rows = rows.withWatermark("ts", late)
    window = F.window("ts", width, slide) if slide else F.window("ts", width)
    each = rows.select("ts", F.explode(as_items(scope)).alias("x"))
    return each.groupBy(window.alias("w"), F.col("x.p").alias("p"), F.col("x.v").alias("v")).agg(F.count("*").alias("freq")).select(F.col("w.start").alias("start"), "p", "v", "freq")


def sessions(rows: DataFrame, key: str, gap: str = "30 minutes", late: str | None = None) -> DataFrame:
    """(key, start, end, n): tuples of one key with no pause longer than ``gap``."""
    if late is not None:
        rows = rows.withWatermark("ts", late)
    return rows.groupBy(F.session_window("ts", gap).alias("w"), key).agg(F.count("*").alias("n")).select(key, F.col("w.start").alias("start"), F.col("w.end").alias("end"), "n")


def distinct_within(rows: DataFrame, scope: list[str], late: str) -> DataFrame:
    """The relation as a set: repeated tuples within the watermark are dropped."""
    return rows.withWatermark("ts", late).dropDuplicatesWithinWatermark(scope)


def assign(rows: DataFrame, c: CompressedRelation) -> DataFrame:
    """``rows`` with the entry that covers each tuple, or -1 for the default table: one static join for each column set.

    Covers of entries are disjoint on the relation they were built from; a new tuple that fits several goes to the first.
    The driver holds column sets, of which a relation of few columns has few; heads stay a table.
    """
    heads = c.heads.select("entry", "items", mask_of(F.col("items")).alias("mask"))
    masks = sorted(r["mask"] for r in heads.select("mask").distinct().collect())
    out, found = rows, []
    for m in masks:
        at = [p for p in range(c.arity) if m >> p & 1]
        side = heads.where(F.col("mask") == m).select(F.col("entry").alias(f"_e{m}"), *[value_at(F.col("items"), p).alias(f"_e{m}_{p}") for p in at])
        out = out.join(side, reduce(lambda a, b: a & b, [F.col(c.scope[p]) == F.col(f"_e{m}_{p}") for p in at]), "left")
        found.append(f"_e{m}")
    first = F.least(*found) if len(found) > 1 else F.col(found[0]) if found else F.lit(None)
    return out.select(*rows.columns, F.coalesce(first, F.lit(-1)).cast("bigint").alias("entry"))


def append(rows: DataFrame, c: CompressedRelation, path: str, checkpoint: str, once: bool = True) -> StreamingQuery:
    """Write new tuples with their entries to a Parquet area; the share of default tuples tells when to build anew."""
    writer = assign(rows, c).writeStream.format("parquet").option("path", path).option("checkpointLocation", checkpoint).outputMode("append")
    return (writer.trigger(availableNow=True) if once else writer).start()


def default_share(assigned: DataFrame) -> DataFrame:
    """(n, n_default, share) of assigned tuples."""
    return assigned.agg(F.count("*").alias("n"), F.count_if(F.col("entry") == -1).alias("n_default")).withColumn("share", F.round(F.col("n_default") / F.greatest(F.col("n"), F.lit(1)), 6))
