"""Shared plumbing of the corpus operators: reading, written intermediates, hashing, connected components."""

from __future__ import annotations

import uuid

import numpy as np
from pyspark.sql import Column, DataFrame, SparkSession
from pyspark.sql import functions as F

from relpress.plans.staging import drop_at_exit, shared_dir, ship

#: Words everywhere: runs of code points other than the six ASCII blanks.
WORD = r"[^\x20\x09-\x0D]+"
#: Rows in one Arrow batch; texts are long, so the default of 10,000 rows is too many for a worker's memory.
BATCH_ROWS = 512
#: Most keys of a join that are broadcast for being hot.
HOT_KEYS = 4096

_M1, _M2 = np.uint64(0xBF58476D1CE4E5B9), np.uint64(0x94D049BB133111EB)
GOLD = np.uint64(0x9E3779B97F4A7C15)


def documents(spark: SparkSession, sf_dir: str) -> DataFrame:
    return spark.read.parquet(f"{sf_dir}/documents.parquet")


def small_batches(spark: SparkSession) -> None:
    """Before Python workers run: they can import this package, and Arrow batches are bounded by rows (a runtime SQL
    setting), so that a worker holds a few MB of text at a time."""
    ship(spark)
    key = "spark.sql.execution.arrow.maxRecordsPerBatch"
    if int(spark.conf.get(key)) > BATCH_ROWS or int(spark.conf.get(key)) <= 0:
        spark.conf.set(key, BATCH_ROWS)


def col(name: str) -> Column:
    """A column by its plain name, whatever characters that has."""
    return F.col("`" + name.replace("`", "``") + "`")


def free_name(docs: DataFrame, name: str) -> str:
    """``name``, with underscores in front until no column of ``docs`` is called so."""
    taken = {c.lower() for c in docs.columns}
    while name.lower() in taken:
        name = f"_{name}"
    return name


def written(spark: SparkSession, df: DataFrame, name: str) -> DataFrame:
    """Write ``df`` to the shared folder and read it back: cuts lineage and survives a lost executor."""
    path = f"{shared_dir(spark)}/relpress-{uuid.uuid4().hex}/{name}"
    # What was shuffled for the table is of no use once it is written: Spark drops those files at the end of the job.
    key = "spark.sql.classic.shuffleDependency.fileCleanup.enabled"
    before = spark.conf.get(key, "false")
    spark.conf.set(key, "true")
    try:
        df.write.parquet(path)
    finally:
        spark.conf.set(key, before)
    drop_at_exit(spark, path)
    out = spark.read.schema(df.schema).parquet(path)
    out._relpress_path = path
    return out


def hot_join(rows: DataFrame, classes: DataFrame, by: list[str], count: str) -> DataFrame:
    """``rows`` joined to ``classes`` (written; one row a key, ``count`` of its rows) on ``by``, split by how often keys stand.

    A key of more than one row in ``HOT_KEYS`` (and more than a thousand) is hot; by that definition there are at most
    ``HOT_KEYS`` of them, whatever the size of the input. Their classes are broadcast, so that their rows stay where they
    are; the others meet in a shuffle, in which no key can be a large part of a task's rows.
    """
    every, most = classes.agg(F.sum(count), F.max(count)).first()
    limit = max((every or 0) // HOT_KEYS, 1000)
    if (most or 0) <= limit:
        return rows.join(classes, by)
    hot = F.broadcast(classes.where(F.col(count) > limit))
    cold = rows.join(F.broadcast(classes.where(F.col(count) > limit).select(*by)), by, "left_anti").join(classes.where(F.col(count) <= limit), by)
    return rows.join(hot, by).unionByName(cold)


def salted_join(rows: DataFrame, classes: DataFrame, by: list[str], count: str, spread: list[str], parts: int = 64) -> DataFrame:
    """As ``hot_join`` for rows that are computed on the way: they pass once, and those of a hot key are dealt over ``parts``
    tasks by a hash of ``spread``, each with a copy of the key's class."""
    every, most = classes.agg(F.sum(count), F.max(count)).first()
    limit = max((every or 0) // HOT_KEYS, 1000)
    if (most or 0) <= limit:
        return rows.join(classes, by)
    hot = F.broadcast(classes.where(F.col(count) > limit).select(*by, F.lit(True).alias("hot_key")))
    salt = F.when(F.col("hot_key"), F.pmod(F.xxhash64(*spread), F.lit(parts)).cast("int")).otherwise(0)
    dealt = rows.join(hot, by, "left").withColumn("salt", salt).drop("hot_key")
    copies = F.when(F.col(count) > limit, F.sequence(F.lit(0), F.lit(parts - 1))).otherwise(F.array(F.lit(0)))
    return dealt.join(classes.withColumn("salt", F.explode(copies)), [*by, "salt"]).drop("salt")


def drop_written(spark: SparkSession, *tables: DataFrame) -> None:
    """Delete intermediates that no later plan reads."""
    jvm = spark.sparkContext._jvm
    conf = spark.sparkContext._jsc.hadoopConfiguration()
    for t in tables:
        path = jvm.org.apache.hadoop.fs.Path(t._relpress_path)
        path.getFileSystem(conf).delete(path, True)


def mix64(h: np.ndarray) -> np.ndarray:
    """Finalise 64-bit words (the public splitmix64 finaliser)."""
    h = (h ^ (h >> np.uint64(30))) * _M1
    h = (h ^ (h >> np.uint64(27))) * _M2
    return h ^ (h >> np.uint64(31))


def connected_components(spark: SparkSession, edges: DataFrame) -> DataFrame:
    """(node, component) of an undirected edge table (a, b); component is its smallest node.

    Alternating large-star and small-star contractions until nothing changes; every step aggregates before it shuffles
    and joins the minimum back, that of a hub by broadcast, so a centre with millions of neighbours is never gathered in
    one task. Empty in, empty out.
    """
    e = written(spark, edges.where("a <> b").select(F.greatest("a", "b").alias("u"), F.least("a", "b").alias("v")).distinct(), "cc")
    before = None
    while True:
        both = e.select("u", "v").union(e.select(F.col("v").alias("u"), F.col("u").alias("v")))
        low = written(spark, both.groupBy("u").agg(F.least(F.min("v"), F.first("u")).alias("m"), F.count("*").alias("n")), "cc_low")
        large = hot_join(both, low, ["u"], "n").where("v > u").select(F.col("v").alias("u"), F.col("m").alias("v")).where("u <> v")
        large = large.unionByName(low.where("u <> m").select("u", F.col("m").alias("v")))
        # A node's minimum after the large step is found among few rows, as most neighbours have gone to their centre.
        low2 = large.groupBy("u").agg(F.min("v").alias("m"))
        small = large.join(low2, "u").select(F.col("v").alias("u"), F.col("m").alias("v")).where("u <> v").unionByName(low2.select("u", F.col("m").alias("v")))
        small = small.select(F.greatest("u", "v").alias("u"), F.least("u", "v").alias("v")).distinct()
        new = written(spark, small, "cc")
        drop_written(spark, e, low)
        e = new
        now = tuple(e.agg(F.count("*"), F.sum(F.hash("u", "v").cast("long")), F.sum(F.xxhash64("u", "v").cast("decimal(38,0)"))).first())
        if now == before:
            break
        before = now
    return e.groupBy("u").agg(F.min("v").alias("component")).withColumnRenamed("u", "node").unionByName(
        e.select(F.col("v").alias("node"), F.col("v").alias("component")).distinct()
    )
