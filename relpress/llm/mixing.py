"""Mixing sources to target weights by fitting each source's budget as a subset sum over document lengths.

Method. Sources in code-point order (null last) weigh 1, 2, 3, repeating; they share the words of the corpus by weight,
stopping at ``cap`` times what they hold, the excess being shared again. A target is met by whole repeats of the source
and a rest, its budget. For the rest, documents are counted by exact length, and a bounded-knapsack table over the counts
of all lengths finds the greatest sum within the budget. A budget of up to ``TABLE`` units is fitted as well as the lengths
allow; of a larger one, all but ``TABLE`` units are first given by an even share of every length, and the table decides
the rest with the counts that are left (exact wherever some choice of these meets the budget, which a few different
lengths suffice for). Of each length, as many documents as were counted are chosen in the order of a seeded hash.

Scale. Only (source, length) counts leave the scan: one row per distinct length of a source, however many documents; the
table takes 5 bytes for each of its bits. Choice within a hot (source, length) goes by hash bucket, so only the bucket
where the count runs out is ordered. The driver sees one row per source, which is what a mix is specified by.

Edge cases. Null or blank texts have size 0 and are taken 0 words; a source of only such texts has target 0. A very long
text is one document of a great length; it is never cut. Repeated rows are separate documents (equal ones may differ in
being chosen; which is chosen does not change any sum). An empty table gives an empty mix. Only the id, text and source
columns are read, so further columns may have any names.
"""

from __future__ import annotations

import math

import numpy as np
import pandas as pd
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F
from pyspark.sql import types as T
from pyspark.sql.window import Window

from .common import WORD, col, small_batches, written

#: Units of the knapsack table at least; hash buckets of a (source, length).
TABLE, BUCKETS = 1 << 22, 1024


def shares(held: list[tuple[str | None, int]], weights: tuple[float, ...] = (1, 2, 3), cap: float = 3.0) -> dict[str | None, float]:
    """Target of each source: the whole by weight, none above ``cap`` times what it holds."""
    order = sorted(held, key=lambda x: (x[0] is None, x[0] or ""))
    weight = {s: weights[i % len(weights)] for i, (s, _) in enumerate(order)}
    size, target = dict(order), {}
    left, open_ = float(sum(size.values())), [s for s, _ in order]
    while open_:
        whole = sum(weight[s] for s in open_)
        over = [s for s in open_ if left * weight[s] / whole > cap * size[s]]
        if not over:
            return target | {s: left * weight[s] / whole for s in open_}
        for s in over:
            target[s] = cap * size[s]
        left -= sum(target[s] for s in over)
        open_ = [s for s in open_ if s not in target]
    return target


def fit(lengths: list[int], counts: list[int], budget: int, table: int = TABLE) -> list[int]:
    """How many documents of each length to take so that their lengths sum to ``budget``, or to just under it.

    The table has a bit for every sum up to ``table`` units (the lengths' common divisor; four times the greatest length if
    that is more) and decides over all counts at once. A budget beyond it first takes an even share of every length, one
    ``table`` short of the budget, and leaves the rest of the counts to the table.
    """
    held = sum(a * b for a, b in zip(lengths, counts))
    if budget >= held:
        return list(counts)
    order = sorted((i for i in range(len(lengths)) if lengths[i] > 0 and counts[i] > 0), key=lambda i: -lengths[i])
    take = [0 if lengths[i] > 0 else counts[i] for i in range(len(lengths))]
    if not order or budget <= 0:
        return take
    unit = math.gcd(*[lengths[i] for i in order])
    even, left, passed = max(0, budget - max(table * unit, 4 * lengths[order[0]])), budget, 0
    if even:
        for i in order:  # what one length can't give of its share passes on to the next
            passed += counts[i] * lengths[i]
            n = min(counts[i], (passed * even // held - (budget - left)) // lengths[i])
            take[i] += n
            left -= n * lengths[i]
    # Counts enter in powers of two and a rest, so each piece is used at most once; heavy pieces first, as they reach far
    # soon. ``by`` has the piece that reached a sum first: what is left without that piece was reached by earlier ones.
    top = left // unit
    whole, reach, pieces = (1 << (top + 1)) - 1, 1, []
    by = np.zeros(top + 1, np.int32)
    for i in order:
        spare, piece = min(counts[i] - take[i], left // lengths[i]), 1
        while spare > 0:
            pieces.append((i, min(piece, spare)))
            spare, piece = spare - pieces[-1][1], piece * 2
    pieces.sort(key=lambda x: (-x[1] * lengths[x[0]], x))
    for at, (i, n) in enumerate(pieces, 1):
        if reach >> top & 1:
            break
        new = reach << (n * lengths[i] // unit) & whole & ~reach
        if new:
            packed = np.frombuffer(new.to_bytes(top // 8 + 1, "little"), np.uint8)
            some = np.flatnonzero(packed)
            bits = np.flatnonzero(np.unpackbits(packed[some], bitorder="little"))
            by[some[bits >> 3] * 8 + (bits & 7)] = at
            reach |= new
    at = reach.bit_length() - 1
    while at:
        i, n = pieces[by[at] - 1]
        take[i] += n
        at -= n * lengths[i] // unit
    return take


def mix(spark: SparkSession, docs: DataFrame, id_col: str = "doc_id", text_col: str = "text", source_col: str = "source", weights: tuple[float, ...] = (1, 2, 3), cap: float = 3.0, seed: int = 7) -> DataFrame:
    """Per document: ``id_col``, ``source_col``, size, source_size, target (of its source), copies, taken (size * copies)."""
    small_batches(spark)
    plain = docs.select(col(id_col).alias("i"), col(source_col).alias("s"), F.coalesce(F.size(F.regexp_extract_all(col(text_col).cast("string"), F.lit(WORD), F.lit(0))), F.lit(0)).cast("long").alias("size"))
    plain = written(spark, plain.withColumn("size", F.when(F.col("size") < 0, 0).otherwise(F.col("size"))), "sizes")
    by_length = written(spark, plain.groupBy("s", "size").agg(F.count("*").alias("n")), "lengths")
    # One row per source: the list of sources is what the mix is specified by, and is small.
    held = [(r["s"], int(r["held"])) for r in by_length.groupBy("s").agg(F.sum(F.col("size") * F.col("n")).alias("held")).collect()]
    target = shares(held, weights, cap)
    kind = T.StructType([T.StructField("s", plain.schema["s"].dataType), T.StructField("source_size", T.LongType()), T.StructField("target", T.DoubleType()), T.StructField("whole", T.LongType()), T.StructField("budget", T.LongType())])
    rows = []
    for s, n in held:
        whole = min(int(target[s] // n), int(cap)) if n else 0
        rows.append((s, n, float(target[s]), whole, 0 if whole >= cap else round(target[s]) - whole * n))
    plan = spark.createDataFrame(rows, kind)

    def fitted(group: pd.DataFrame) -> pd.DataFrame:
        group = group.sort_values("size").reset_index(drop=True)
        return group[["s", "size", "n", "source_size", "target", "whole"]].assign(take=fit(group["size"].tolist(), group["n"].tolist(), int(group["budget"].iloc[0])))

    same = F.col("x.s").eqNullSafe(F.col("y.s"))
    counted = by_length.alias("x").join(F.broadcast(plan).alias("y"), same).select("x.s", "x.size", "x.n", "source_size", "target", "whole", "budget")
    chosen = written(spark, counted.groupBy("s").applyInPandas(fitted, T.StructType([by_length.schema["s"], *T._parse_datatype_string("size long, n long, source_size long, target double, whole long, take long").fields])), "chosen")

    h = F.xxhash64(F.lit(seed), F.col("i"))
    hashed = plain.withColumn("h", h).withColumn("bucket", F.pmod(F.shiftrightunsigned("h", 20), F.lit(BUCKETS)).cast("int"))
    buckets = hashed.groupBy("s", "size", "bucket").agg(F.count("*").alias("in_bucket"))
    some = chosen.where("take > 0 and take < n")
    on = F.col("x.s").eqNullSafe(F.col("y.s")) & (F.col("x.size") == F.col("y.size"))
    cut = buckets.alias("x").join(some.alias("y"), on).select("x.s", "x.size", "x.bucket", "in_bucket", "take")
    cut = cut.withColumn("before", F.sum("in_bucket").over(Window.partitionBy("s", "size").orderBy("bucket")) - F.col("in_bucket"))
    cut = written(spark, cut.select("s", "size", "bucket", F.greatest(F.lit(0), F.least(F.col("take") - F.col("before"), F.col("in_bucket"))).alias("want"), "in_bucket"), "buckets")

    out = hashed.alias("x").join(chosen.alias("y"), on).select("x.*", "n", "source_size", "target", "whole", "take")
    out = out.alias("x").join(cut.alias("y"), on & (F.col("x.bucket") == F.col("y.bucket")), "left").select("x.*", "want", "in_bucket")
    # Ordered only where a bucket is taken in part.
    part = (F.col("want") > 0) & (F.col("want") < F.col("in_bucket"))
    rank = F.row_number().over(Window.partitionBy("s", "size", "bucket").orderBy("h", "i"))
    settled = out.where(~F.coalesce(part, F.lit(False))).withColumn("picked", F.when(F.col("take") >= F.col("n"), 1).when(F.col("take") == 0, 0).otherwise((F.coalesce("want", F.lit(0)) > 0).cast("int")))
    ranked = out.where(part).withColumn("picked", (rank <= F.col("want")).cast("int"))
    both = settled.unionByName(ranked).withColumn("copies", F.col("whole") + F.col("picked"))
    return both.select(F.col("i").alias(id_col), F.col("s").alias(source_col), "size", "source_size", "target", "copies", (F.col("copies") * F.col("size")).alias("taken"))
