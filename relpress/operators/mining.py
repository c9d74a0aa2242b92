"""Frequent itemsets of a relation: all, closed, maximal and the top k, by two engines.

The lattice engine counts with one CUBE (a tuple has one value per column, so every itemset is a grouping-set row); it is
for up to a dozen columns. The level-wise form counts only grouping sets whose parents have survivors. The shard engine
sends each tuple to the shard of every frequent item it holds and enumerates closed sets there by closure extension;
a set is found in the shard of its rarest item only, where its whole cover is, so no global pass follows. A shard with
more rows than a task should hold is split by its next item, again and again if need be.

All return (items, len, freq); frequencies count tuples, ``freq >= s_min``.
"""

from __future__ import annotations

import heapq
from collections.abc import Iterator

import numpy as np
import pandas as pd
from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F
from pyspark.sql.window import Window

from ..functions.itemsets import ITEMS, as_items, masked, without_each
from ..model import Relation

#: Columns up to which the cube may be asked for, and up to which ``candidates`` takes it: it multiplies each tuple by two
#: to the power of the columns, before any count, while a shard engine sends it once for each column.
CUBE_COLUMNS, CUBE_TAKEN = 12, 6
#: Distinct rows of a shard beyond which it is split by its next item.
SHARD_ROWS = 200_000
FREE = f"items {ITEMS}, len int, freq bigint"


def frequent_items(rel: Relation, s_min: int) -> DataFrame:
    """Sets of one item: (p, v, freq)."""
    x = rel.df.select(F.explode(as_items(rel.scope)).alias("x"))
    return x.groupBy(F.col("x.p").alias("p"), F.col("x.v").alias("v")).agg(F.count("*").alias("freq")).where(F.col("freq") >= s_min)


def frequent(rel: Relation, s_min: int, max_len: int | None = None) -> DataFrame:
    """All frequent itemsets with the lattice engine."""
    if rel.arity > CUBE_COLUMNS:
        raise ValueError(f"{rel.arity} columns: use the level-wise form or the shard engine")
    cols = rel.scope
    mask = sum(((1 - F.grouping(c).cast("bigint")) * (1 << i) for i, c in enumerate(cols)), F.lit(0))
    counted = rel.df.cube(*cols).agg(F.count("*").alias("freq"), mask.cast("bigint").alias("mask")).where((F.col("freq") >= s_min) & (F.col("mask") > 0))
    out = counted.select(as_items(cols, F.col("mask")).alias("items"), F.bit_count("mask").cast("int").alias("len"), "freq")
    return out if max_len is None else out.where(F.col("len") <= max_len)


def frequent_levelwise(rel: Relation, s_min: int, max_len: int | None = None) -> DataFrame:
    """All frequent itemsets, a level at a time: only masks all of whose parents have frequent sets are counted.

    The driver holds masks (column sets), never itemsets.
    """
    a, out, alive = rel.arity, [], None
    base = rel.df.select(as_items(rel.scope).alias("t"))
    for level in range(1, (max_len or a) + 1):
        if alive is None:
            masks = [1 << i for i in range(a)]
        else:
            masks = sorted({m | 1 << i for m in alive for i in range(a) if not m >> i & 1 and all((m | 1 << i) & ~(1 << j) in alive for j in range(a) if (m | 1 << i) >> j & 1)})
        if not masks:
            break
        listed = F.explode(F.array(*[F.lit(m).cast("bigint") for m in masks]))
        rows = base.select("t", listed.alias("mask")).select("mask", masked(F.col("t"), F.col("mask")).alias("items"))
        sets = rows.groupBy("mask", "items").agg(F.count("*").alias("freq")).where(F.col("freq") >= s_min)
        from ..plans.staging import staged

        sets = staged(sets, f"level{level}")
        alive = {r["mask"] for r in sets.select("mask").distinct().collect()}
        out.append(sets.select("items", F.lit(level).alias("len"), "freq"))
    return _union(out) if out else rel.df.sparkSession.createDataFrame([], FREE)


def _union(parts: list[DataFrame]) -> DataFrame:
    out = parts[0]
    for p in parts[1:]:
        out = out.unionByName(p)
    return out


def parents_of(sets: DataFrame) -> DataFrame:
    """(items, freq): every set one item smaller, with the largest frequency of the sets it came from."""
    return sets.where("len > 1").select(F.explode(without_each(F.col("items"))).alias("items"), "freq").groupBy("items").agg(F.max("freq").alias("above"))


def frequent_growth(transactions: DataFrame, s_min: int, column: str = "items") -> DataFrame:
    """(items, freq) of set-valued transactions, by the library's parallel growth of frequent patterns.

    Its threshold is a share, so one just under ``s_min`` is asked for and the integer threshold is applied to the counts.
    """
    from pyspark.ml.fpm import FPGrowth

    n = transactions.count()
    found = FPGrowth(itemsCol=column, minSupport=max(0.0, (s_min - 0.5) / max(1, n))).fit(transactions).freqItemsets
    return found.where(F.col("freq") >= s_min).select(F.array_sort("items").alias("items"), "freq")


def closed(frequent_sets: DataFrame) -> DataFrame:
    """Sets without a superset of equal frequency; immediate supersets tell."""
    return frequent_sets.join(parents_of(frequent_sets), "items", "left").where("above IS NULL OR above < freq").drop("above")


def maximal(frequent_sets: DataFrame) -> DataFrame:
    """Sets without a frequent superset."""
    return frequent_sets.join(parents_of(frequent_sets).select("items"), "items", "left_anti")


class _Bits:
    """Tuples by items as words of 64 tuples, with weighted counts of covers."""

    def __init__(self, rows: np.ndarray, weight: np.ndarray):
        n = -(-len(rows) // 64) * 64
        bits = np.zeros((rows.shape[1], n), bool)
        bits[:, : len(rows)] = rows.T
        self.cols = np.packbits(bits, axis=1).view(np.uint64)
        self.planes = []
        for b in range(int(weight.max()).bit_length() if len(weight) else 0):
            plane = np.zeros(n, bool)
            plane[: len(rows)] = weight >> b & 1
            self.planes.append((1 << b, np.packbits(plane).view(np.uint64)))

    def cover(self, items) -> np.ndarray:
        return np.bitwise_and.reduce(self.cols[items])

    def size(self, cover: np.ndarray) -> int:
        return sum(w * int(np.bitwise_count(cover & plane).sum()) for w, plane in self.planes)

    def counts(self, cover: np.ndarray) -> np.ndarray:
        """For every item, the weight of the cover's tuples that hold it."""
        return sum(w * np.bitwise_count(self.cols & (cover & plane)).sum(axis=1, dtype=np.int64) for w, plane in self.planes)


#: Words of a shard up to which all covers are bit vectors; larger ones are cut down to the covered rows as they are refined.
BIT_WORDS = 1 << 16


def enumerate_closed(rows: np.ndarray, weight: np.ndarray, prefix: list[int], s_min: int, only_maximal: bool) -> Iterator[tuple[np.ndarray, int]]:
    """Closed (or maximal) sets of one shard, whose rarest items are ``prefix``. ``rows`` is tuples by items, rarest first.

    Depth first without a store of what was found: a branch extends by items after the last one chosen, and is left if
    the closure brings in an item before that one that the branch did not hold, as another branch meets that set.
    """
    small = rows.shape[1] * -(-len(rows) // 64) <= BIT_WORDS
    bits = _Bits(rows, weight) if small else None
    held = np.zeros(rows.shape[1], bool)
    held[prefix] = True
    stack = [(bits.cover(prefix) if small else np.flatnonzero(rows[:, prefix].all(axis=1)), prefix[-1], held)]
    while stack:
        cover, core, held = stack.pop()
        if small:
            total, counts = bits.size(cover), bits.counts(cover)
        else:
            sub, w = rows[cover], weight[cover]
            total, counts = int(w.sum()), w @ sub
        closure = counts == total
        if total < s_min or (closure[:core] & ~held[:core]).any():
            continue
        more = (counts >= s_min) & ~closure
        if not (only_maximal and more.any()):
            yield np.flatnonzero(closure), total
        for j in np.flatnonzero(more[core + 1 :]) + core + 1:
            stack.append((cover & bits.cols[j] if small else cover[sub[:, j]], int(j), closure))


def enumerate_top(rows: np.ndarray, weight: np.ndarray, starts: list[list[int]], s_min: int, most: int) -> Iterator[tuple[np.ndarray, int]]:
    """The ``most`` most frequent closed sets whose rarest items are one of ``starts``, most frequent first; ties are cut.

    Best first: a branch is no more frequent than the set it extends, so what comes off the heap is the next in order and
    nothing under the last set wanted is ever looked at. Covers are bit vectors, found again from the set when needed.
    """
    bits = _Bits(rows, weight)
    heap, made = [], len(starts)
    for n_, prefix in enumerate(starts):
        heap.append((-bits.size(bits.cover(prefix)), n_, prefix[-1], np.array(prefix), np.array(prefix)))
    heapq.heapify(heap)
    while heap and most > 0:
        total, _, core, held, chosen = heapq.heappop(heap)
        total = -total
        if total < s_min:
            break
        counts = bits.counts(bits.cover(chosen))
        closure = np.flatnonzero(counts == total)
        early = closure[closure < core]
        if len(early) and not np.isin(early, held, assume_unique=True).all():
            continue
        yield closure, total
        most -= 1
        wide = counts[core + 1 :]
        for j in np.flatnonzero((wide >= s_min) & (wide < total)) + core + 1:
            heapq.heappush(heap, (-int(counts[j]), made, int(j), closure, np.append(closure, j)))
            made += 1


def _shards(rel: Relation, s_min: int, only_maximal: bool, most_rows: int, most: int | None = None) -> DataFrame:
    from ..plans.staging import ship, staged

    ship(rel.df.sparkSession)
    items = frequent_items(rel, s_min)
    # The order of items, rare to frequent: increasing numbers along a sort by ranges, not dense.
    order = staged(items.orderBy("freq", "p", "v").select("p", "v", F.monotonically_increasing_id().alias("o")), "items")
    tuples = rel.df.select(F.explode(as_items(rel.scope)).alias("x"), *rel.scope)
    held = tuples.join(order, (F.col("x.p") == F.col("p")) & (F.col("x.v") == F.col("v"))).groupBy(*rel.scope).agg(F.sort_array(F.collect_list(F.struct("o", "p", "v"))).alias("s"))
    # Tuples that agree on their frequent items are one row with a weight.
    rows = held.groupBy("s").agg(F.count("*").alias("w"))
    sent = rows.select("w", F.explode("s").alias("x"), "s").select(F.array("x.o").alias("prefix"), "w", "s")

    def mine(key: tuple, group: pd.DataFrame) -> pd.DataFrame:
        # Plain arrays of numbers: a row of structs would be a dictionary an item.
        weight, lengths = group["w"].to_numpy(np.int64), group["o"].map(len).to_numpy()
        row = np.repeat(np.arange(len(group)), lengths)
        named, first, at = np.unique(np.concatenate(list(group["o"])), return_index=True, return_inverse=True)
        held = np.zeros(len(named), np.int64)
        np.add.at(held, at, weight[row])
        # What is rare within the shard is in none of its sets, and makes no column.
        often = held >= s_min
        names = named[often]
        if not np.isin(key[0], names).all():
            return pd.DataFrame({"items": pd.Series([], dtype=object), "len": [], "freq": []})
        column = np.cumsum(often) - 1
        rows = np.zeros((len(group), len(names)), bool)
        rows[row[often[at]], column[at[often[at]]]] = True
        ps, vs = np.concatenate(list(group["p"]))[first[often]], np.concatenate(list(group["v"]))[first[often]]
        place = [(int(p), int(v) if v == v else None) for p, v in zip(ps, vs)]
        prefix = np.searchsorted(names, key[0]).tolist()
        found = list(enumerate_closed(rows, weight, prefix, s_min, only_maximal) if most is None else enumerate_top(rows, weight, [prefix], s_min, most))
        sets = [sorted(place[i] for i in s) for s, _ in found]
        return pd.DataFrame({"items": pd.Series([[{"p": p, "v": v} for p, v in s] for s in sets], dtype=object), "len": [len(s) for s in sets], "freq": [f for _, f in found]})

    def mined(shards: DataFrame) -> DataFrame:
        return shards.select("prefix", "w", *[F.col(f"s.{c}").alias(c) for c in "opv"]).groupBy("prefix").applyInPandas(mine, FREE)

    out = []
    while True:
        # A shard of more rows than a task should hold is split by its next item.
        sizes = sent.groupBy("prefix").agg(F.count("*").alias("n"))
        large = staged(sizes.where(F.col("n") > most_rows).select("prefix"), "large")
        if large.isEmpty():
            out.append(mined(sent))
            return _union(out)
        out.append(mined(sent.join(large, "prefix", "left_anti")))
        big = staged(sent.join(large, "prefix", "left_semi"), "split")
        counts = staged(big.select("prefix", "w", F.explode("s").alias("x")).groupBy("prefix", "x").agg(F.sum("w").alias("f")), "counts")
        # The prefix is a set itself where no other item goes as often with it (or, for maximal ones, often enough).
        other = F.when(F.array_contains("prefix", F.col("x.o")), F.lit(0)).otherwise(F.col("f"))
        own = F.filter(F.collect_list(F.when(F.array_contains("prefix", F.col("x.o")), F.struct("x.p", "x.v"))), lambda x: x.isNotNull())
        alone = counts.groupBy("prefix").agg(F.max("f").alias("freq"), F.max(other).alias("next"), F.array_sort(own).alias("items"))
        fits = (F.col("next") < s_min) if only_maximal else (F.col("next") < F.col("freq"))
        out.append(alone.where(fits & (F.col("freq") >= s_min)).select("items", F.size("items").alias("len"), "freq"))
        deeper = big.select("prefix", "w", "s", F.explode("s").alias("x")).where(F.col("x.o") > F.element_at("prefix", -1))
        often = counts.where(F.col("f") >= s_min).select(F.col("prefix").alias("_p"), F.col("x.o").alias("_o"))
        deeper = deeper.join(often, (F.col("prefix") == F.col("_p")) & (F.col("x.o") == F.col("_o")))
        sent = staged(deeper.select(F.concat("prefix", F.array("x.o")).alias("prefix"), "w", "s"), "deeper")


def closed_shards(rel: Relation, s_min: int, most_rows: int = SHARD_ROWS) -> DataFrame:
    """Closed frequent itemsets with the shard engine."""
    return _shards(rel, s_min, False, most_rows)


def maximal_shards(rel: Relation, s_min: int, most_rows: int = SHARD_ROWS) -> DataFrame:
    """Maximal frequent itemsets with the shard engine."""
    return _shards(rel, s_min, True, most_rows)


def top_closed_shards(rel: Relation, k: int, s_min: int = 2, most_rows: int = SHARD_ROWS) -> DataFrame:
    """Closed sets among which are ``k`` of the most frequent ones: the ``k`` most frequent of every shard.

    No threshold is needed and none but the sets near the top is enumerated, so the k-th frequency of a relation with
    millions of closed sets costs k sets a shard.
    """
    return _shards(rel, s_min, False, most_rows, k)


def top(sets: DataFrame, k: int, by: Column | None = None, ties: str = "cut") -> DataFrame:
    """The ``k`` sets of highest score (frequency where None); ``ties`` 'include' adds those equal to the k-th.

    With ties, a histogram of scores finds the k-th one: as many rows as there are scores, however many sets.
    """
    d = sets.withColumn("_score", F.col("freq") if by is None else by)
    if ties == "cut":
        return d.orderBy(F.desc("_score"), "items").limit(k).drop("_score")
    return d.join(F.broadcast(_last_score(d, k)), F.col("_score") >= F.col("_least")).drop("_score", "_least")


def _last_score(d: DataFrame, k: int) -> DataFrame:
    counts = d.groupBy("_score").agg(F.count("*").alias("n"))
    run = counts.withColumn("before", F.sum("n").over(Window.orderBy(F.desc("_score"))) - F.col("n"))
    return run.where(F.col("before") < k).agg(F.min("_score").alias("_least"))


def top_frequencies(sets: DataFrame, k: int) -> DataFrame:
    """(freq, n): the histogram of the k highest frequencies (ties cut), from the histogram of all."""
    counts = sets.groupBy("freq").agg(F.count("*").alias("n"))
    run = counts.withColumn("before", F.sum("n").over(Window.orderBy(F.desc("freq"))) - F.col("n"))
    return run.where(F.col("before") < k).select("freq", F.least(F.col("n"), F.lit(k) - F.col("before")).alias("n"))


def threshold(sets: DataFrame, k: int, reduce: str = "min", least: int = 2) -> int:
    """Support threshold from the k most frequent closed sets: their least or mean frequency (rounded up), at least 2."""
    if k <= 0:
        return least
    h = top_frequencies(sets, k)
    value = h.agg(F.min("freq") if reduce == "min" else F.ceil(F.sum(F.col("freq") * F.col("n")) / F.sum("n"))).first()[0]
    return max(least, int(value or least))


def count_of(k: float | int, tuples: int) -> int:
    """k as a count, or as a share of the tuples (a float)."""
    return -int(-k * tuples // 1) if isinstance(k, float) else int(k)


def curve(sets: DataFrame, grid: list[int]) -> DataFrame:
    """(threshold, n_sets): how many of the given sets reach each threshold; too many says too low, too few too high."""
    g = sets.sparkSession.createDataFrame([(int(x),) for x in grid], "threshold int")
    counts = sets.groupBy("freq").agg(F.count("*").alias("n"))
    return counts.join(F.broadcast(g), F.col("freq") >= F.col("threshold"), "right").groupBy("threshold").agg(F.coalesce(F.sum("n"), F.lit(0)).cast("bigint").alias("n_sets"))
