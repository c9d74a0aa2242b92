"""Greedy choice of itemsets with disjoint covers, in a total order: score down, then item list up.

``greedy`` gives the sequential result in parallel rounds: a set wins a round if it comes first among the live sets at
every tuple it covers. In a round each tuple names its first live set and each set counts the tuples that name it, so a
round costs two aggregations of the live covers and no comparison of sets with each other.

``greedy_bits`` is the same choice where sets cover so much that their covers as rows would be larger than as bit vectors:
blocks of tuples are walked with all live sets, and no cover is written but those of chosen sets.
"""

from __future__ import annotations

import numpy as np
import pandas as pd
from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

from ..functions.itemsets import covers, masked, mask_of, score
from ..plans.staging import ship, staged

#: Tuples in a block of bit vectors.
BLOCK = 1 << 16


def rank(sets: DataFrame, arity: int, objective: str = "area") -> DataFrame:
    """Candidates with score and an increasing number ``rank`` in the order of choice (not dense), written."""
    scored = sets.withColumn("score", score(objective, F.col("len"), F.col("freq"), arity))
    return staged(scored.orderBy(F.desc("score"), "items").withColumn("rank", F.monotonically_increasing_id()), "ranked")


def cover(sets: DataFrame, tuples: DataFrame) -> DataFrame:
    """(rank, tid): which tuples each set covers.

    Few column sets: a tuple meets the sets of a column set by its own part on these columns, one equality join whatever
    the number of sets. Many of them: a set is posted under its two rarest items, a tuple meets it there by its pairs of
    items, and the whole set is compared. The driver holds the column sets in use, one bit pattern each.
    """
    with_mask = sets.select("rank", "items", mask_of(F.col("items")).alias("mask"))
    masks = [r["mask"] for r in with_mask.select("mask").distinct().collect()]
    if not masks:
        return tuples.select(F.lit(0).cast("bigint").alias("rank"), "tid").where("false")
    a = max(masks).bit_length()
    if len(masks) > a * (a + 1) // 2:
        return _cover_by_rarest(sets.select("rank", "items"), tuples)
    parts = tuples.select("tid", "items", F.explode(F.array(*[F.lit(m).cast("bigint") for m in sorted(masks)])).alias("mask"))
    parts = parts.select("tid", masked(F.col("items"), F.col("mask")).alias("items"))
    return parts.join(with_mask.select("rank", "items"), "items").select("rank", "tid")


def _cover_by_rarest(sets: DataFrame, tuples: DataFrame) -> DataFrame:
    count = tuples.select(F.explode("items").alias("x")).groupBy("x").agg(F.count("*").alias("f"))
    each = sets.select("rank", F.explode("items").alias("x")).join(count, "x")
    rare = each.groupBy("rank").agg(F.slice(F.sort_array(F.collect_list(F.struct("f", "x"))), 1, 2).alias("r"))  # at most a tuple's items
    post = rare.select("rank", F.array_sort(F.transform("r", lambda z: z["x"])).alias("at")).join(sets, "rank")
    pairs = F.flatten(F.transform("items", lambda x: F.transform(F.filter("items", lambda y: y["p"] >= x["p"]), lambda y: F.array_distinct(F.array(x, y)))))
    met = tuples.select("tid", F.col("items").alias("t"), F.explode(pairs).alias("at"))
    # Tuples by their pairs are many more rows than Spark's estimate has: never broadcast.
    return met.join(post.hint("merge"), "at").where(covers(F.col("items"), F.col("t"))).select("rank", "tid")


def greedy(sets: DataFrame, covers: DataFrame, overlap: str = "drop", arity: int | None = None, objective: str = "area", least: int = 2) -> tuple[DataFrame, int]:
    """(rank, tid, head) of the chosen sets, and the number of rounds; each round chooses one set at least.

    ``overlap`` 'drop' leaves out every set that shares a tuple with a chosen one. 'shrink' takes chosen tuples from the
    other covers and scores what is left, as long as ``least`` tuples are; scores only fall, so a set that comes first at
    all its tuples can't be overtaken.
    """
    if overlap not in ("drop", "shrink"):
        raise ValueError(f"no overlap mode {overlap!r}")
    live = staged(covers.join(sets.select("rank", "items", "len", "score"), "rank"), "covers")
    won, rounds = [], 0
    while not live.isEmpty():
        rounds += 1
        place = F.struct((-F.col("score")).alias("s"), "items", "rank")
        first = live.groupBy("tid").agg(F.min(place).alias("first")).select("tid", F.col("first.rank").alias("rank"), F.lit(1).alias("mine"))
        size = live.groupBy("rank").agg(F.count("*").alias("n"))
        ahead = first.groupBy("rank").agg(F.count("*").alias("m")).join(size, "rank").where("m = n").select("rank")
        taken = staged(live.join(ahead, "rank", "left_semi").select("rank", "tid", F.col("items").alias("head")), f"won{rounds}")
        won.append(taken)
        rest = live.join(taken.select("rank").distinct(), "rank", "left_anti")
        if overlap == "drop":
            lost = rest.join(taken.select("tid"), "tid", "left_semi").select("rank").distinct()
            rest = rest.join(lost, "rank", "left_anti")
        else:
            rest = rest.join(taken.select("tid"), "tid", "left_anti")
            size = rest.groupBy("rank").agg(F.count("*").alias("freq")).where(F.col("freq") >= least)
            rest = rest.drop("score").join(size, "rank").withColumn("score", score(objective, F.col("len"), F.col("freq"), arity or 1)).drop("freq")
            rest = rest.select(live.columns)
        live = staged(rest, f"live{rounds}")
    if not won:
        return live.select("rank", "tid", F.col("items").alias("head")), 0
    out = won[0]
    for w in won[1:]:
        out = out.unionByName(w)
    return out, rounds


def _coded(items: Column) -> Column:
    """Items as plain numbers, a null value as one beyond all others."""
    return F.transform(items, lambda x: x["p"] * F.lit(1 << 33) + F.coalesce(x["v"].cast("bigint"), F.lit(1 << 31)) + F.lit(1 << 31))


class _Block:
    """A block's tuples as one bit vector an item."""

    def __init__(self, items: pd.Series):
        self.n, self.bits = len(items), {}
        for column in np.stack(list(items)).T if self.n else []:
            for code in np.unique(column):
                self.bits[int(code)] = np.packbits(column == code)
        self.none = np.packbits(np.zeros(self.n, bool))

    def cover(self, items) -> np.ndarray:
        return np.bitwise_and.reduce([self.bits.get(int(x), self.none) for x in items])


def greedy_bits(sets: DataFrame, tuples: DataFrame) -> tuple[DataFrame, int]:
    """As ``greedy`` with 'drop' for sets numbered by ``rank`` in the order of choice, by bit vectors of blocks of tuples.

    In a round every block names the live sets that are not first at one of its tuples; the others are chosen. Then it gives
    the chosen sets' tuples and names the sets that share one of them.
    """
    spark = sets.sparkSession
    ship(spark)
    blocks = max(1, -(-tuples.count() // BLOCK))
    dealt = staged(tuples.select(F.pmod(F.xxhash64("tid"), F.lit(blocks)).alias("block"), "tid", _coded(F.col("items")).alias("items")), "blocks")

    def late(block: pd.DataFrame, live: pd.DataFrame) -> pd.DataFrame:
        held, out = _Block(block["items"]), []
        seen = held.none.copy()
        for r, items in live.sort_values("rank")[["rank", "items"]].itertuples(index=False):
            c = held.cover(items)
            if (c & seen).any():
                out.append(r)
            seen |= c
        return pd.DataFrame({"rank": np.array(out, np.int64)})

    def settle(block: pd.DataFrame, live: pd.DataFrame) -> pd.DataFrame:
        held, out = _Block(block["items"]), []
        tid, taken = block["tid"].to_numpy(np.int64), held.none.copy()
        for r, items in live[live["won"]][["rank", "items"]].itertuples(index=False):
            c = held.cover(items)
            taken |= c
            mine = tid[np.unpackbits(c, count=held.n).astype(bool)]
            out.append(pd.DataFrame({"rank": np.full(len(mine), r, np.int64), "tid": pd.Series(mine, dtype="Int64")}))
        lost = [r for r, items in live[~live["won"]][["rank", "items"]].itertuples(index=False) if (held.cover(items) & taken).any()]
        out.append(pd.DataFrame({"rank": np.array(lost, np.int64), "tid": pd.Series([None] * len(lost), dtype="Int64")}))
        return pd.concat(out)

    def by_block(live: DataFrame, f, schema: str) -> DataFrame:
        each = live.withColumn("block", F.explode(F.sequence(F.lit(0).cast("bigint"), F.lit(blocks - 1).cast("bigint"))))
        return dealt.groupBy("block").cogroup(each.groupBy("block")).applyInPandas(f, schema)

    live = staged(sets.select("rank", _coded(F.col("items")).alias("items")), "live")
    won, rounds = [], 0
    while not live.isEmpty():
        rounds += 1
        after = staged(by_block(live, late, "rank long"), f"late{rounds}").select("rank", F.lit(True).alias("late")).distinct()
        judged = staged(live.join(after, "rank", "left").select("rank", "items", F.col("late").isNull().alias("won")), f"judged{rounds}")
        gone = staged(by_block(judged, settle, "rank long, tid long"), f"settled{rounds}")
        won.append(gone.where("tid IS NOT NULL"))
        live = staged(judged.where("NOT won").join(gone.where("tid IS NULL").select("rank").distinct(), "rank", "left_anti").select("rank", "items"), f"live{rounds}")
    heads = sets.select("rank", F.col("items").alias("head"))
    if not won:
        return tuples.join(heads.where("false"), F.lit(True)).select("rank", "tid", "head"), 0
    out = won[0]
    for w in won[1:]:
        out = out.unionByName(w)
    return out.join(heads, "rank").select("rank", "tid", "head"), rounds


def greedy_local(sets: list[tuple], covers: dict, overlap: str = "drop", score_of=None, least: int = 2) -> list[tuple]:
    """The sequential choice on the driver, for small inputs and as a test oracle.

    ``sets`` are (items, len); ``covers`` gives each index its tuples. Returns (items, tuples) in the order chosen.
    """
    score_of = score_of or (lambda length, n: length * n)
    live = {i: set(c) for i, c in covers.items()}
    out = []
    while live:
        i = min(live, key=lambda j: (-score_of(sets[j][1], len(live[j])), sets[j][0]))
        taken = live.pop(i)
        out.append((sets[i][0], taken))
        if overlap == "drop":
            live = {j: c for j, c in live.items() if not c & taken}
        else:
            live = {j: c - taken for j, c in live.items() if len(c - taken) >= least}
    return out
