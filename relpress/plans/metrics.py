"""Measures of relations, compression, filtering and solving."""

from __future__ import annotations

from pyspark.sql import DataFrame
from pyspark.sql import functions as F
from pyspark.sql.window import Window

from ..functions.itemsets import local_rate, saving
from ..model import CompressedRelation, Relation


def cells(rel: Relation) -> DataFrame:
    """(tuples, arity, cells)."""
    return rel.df.agg(F.count("*").alias("tuples")).select("tuples", F.lit(rel.arity).alias("arity"), (F.col("tuples") * rel.arity).alias("cells"))


def entry_sizes(heads: DataFrame, arity: int) -> DataFrame:
    """Each entry's cells before and after, and its own rate."""
    return heads.select("entry", "len", "freq", (F.col("freq") * arity).alias("before"), (F.col("len") + (arity - F.col("len")) * F.col("freq")).alias("after"), local_rate(F.col("len"), F.col("freq"), arity).alias("local_rate"))


def compression_report(c: CompressedRelation) -> DataFrame:
    """tuples, cells, n_used, covered, saved, compressed_share, table_rate, mean_len, mean_freq (one row)."""
    used = c.heads.agg(F.count("*").alias("n_used"), F.coalesce(F.sum("freq"), F.lit(0)).alias("covered"), F.coalesce(F.sum(saving(F.col("len"), F.col("freq"))), F.lit(0)).alias("saved"), F.avg("len").alias("mean_len"), F.avg("freq").alias("mean_freq"))
    rest = c.default.agg(F.count("*").alias("uncovered"))
    d = used.crossJoin(rest).withColumn("tuples", F.col("covered") + F.col("uncovered"))  # one row each
    d = d.withColumn("cells", F.col("tuples") * c.arity)

    def part(a: str, b: str):
        return F.when(F.col(b) > 0, F.round(F.col(a) / F.col(b), 6)).otherwise(F.lit(0.0))

    return d.select(
        "tuples", "cells", "n_used", "covered", "saved", part("covered", "tuples").alias("compressed_share"), part("saved", "cells").alias("table_rate"),
        F.round(F.coalesce("mean_len", F.lit(0.0)), 6).alias("mean_len"), F.round(F.coalesce("mean_freq", F.lit(0.0)), 6).alias("mean_freq"),
    )


def solved(runs: DataFrame, *by: str) -> DataFrame:
    """Per method (and ``by``): instances, solved within the limit, and mean CPU seconds of the solved (null when none was)."""
    done = F.col("status") != "timeout"
    return runs.groupBy(*by, "method").agg(F.count("*").alias("instances"), F.count_if(done).alias("solved"), F.avg(F.when(done, F.col("cpu_s"))).alias("mean_cpu_s"))


def cactus(runs: DataFrame, cost: str = "cpu_s", *by: str) -> DataFrame:
    """(by, method, solved, total): running sum of sorted costs of the solved instances."""
    w = Window.partitionBy(*by, "method").orderBy(cost, "instance_id")
    return runs.where("status <> 'timeout'").select(*by, "method", F.row_number().over(w).alias("solved"), F.sum(cost).over(w.rowsBetween(Window.unboundedPreceding, 0)).alias("total"))


def dominance(curve: DataFrame, one: str, two: str) -> DataFrame:
    """(solved, lead): at which counts the curve of ``one`` lies under (-1), on (0) or over (1) that of ``two``, where that changes."""
    a = curve.where(F.col("method") == one).select("solved", F.col("total").alias("a"))
    b = curve.where(F.col("method") == two).select("solved", F.col("total").alias("b"))
    d = a.join(b, "solved").select("solved", F.signum(F.col("a") - F.col("b")).cast("int").alias("lead"))
    before = F.lag("lead").over(Window.orderBy("solved"))
    return d.withColumn("before", before).where("before IS NULL OR before <> lead").drop("before")


def characteristics(variables: DataFrame, domains: DataFrame, constraints: DataFrame, relations: DataFrame) -> DataFrame:
    """Per workload: instances, and the largest numbers of variables, values, relations, tuples, columns and constraints.

    ``variables`` (workload, instance_id, var), ``domains`` (instance_id, var, code), ``constraints`` (instance_id, cid,
    rel_id, arity), ``relations`` (rel_id, tuples).
    """
    v = variables.groupBy("workload", "instance_id").agg(F.count("*").alias("n_vars"))
    d = domains.groupBy("instance_id", "var").agg(F.count("*").alias("n")).groupBy("instance_id").agg(F.max("n").alias("n_values"))
    c = constraints.join(relations, "rel_id").groupBy("instance_id").agg(F.count("*").alias("n_constraints"), F.countDistinct("rel_id").alias("n_relations"), F.max("tuples").alias("n_tuples"), F.max("arity").alias("n_columns"))
    top = [F.max(x).alias(f"max_{x[2:]}") for x in ("n_vars", "n_values", "n_relations", "n_tuples", "n_columns", "n_constraints")]
    return v.join(d, "instance_id").join(c, "instance_id").groupBy("workload").agg(F.count("*").alias("instances"), *top)
