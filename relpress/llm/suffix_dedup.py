"""Exact substring deduplication by bucket-pointer refinement over content-chosen suffixes.

Every byte that lies in a string of ``least`` bytes which also starts earlier is removed; texts are UTF-8 bytes, and
strings do not cross documents.

Method. Suffixes are put into buckets by their first ``Q`` bytes, and buckets are refined by the bucket identifiers found
at later offsets, the identifier of a longer stretch being built from those at all places in it, by running sums, so that
work on one offset serves all suffixes before it. Only suffixes that can matter take part:

1. Of the q-gram buckets inside a string of ``least`` bytes, the one with the least identifier is its anchor; equal
   strings have equal anchors. The strings of one anchor start in one stretch of text (a segment). A bucket with a single
   anchor in the corpus holds no repeat and is dropped: of unique text nothing else is ever shuffled. The first pass over
   the text names anchors only, the second one segments too.
2. Segments of the remaining buckets are refined by the identifiers at their later offsets. Later copies of an equal
   segment are removed whole.
3. Where a bucket still holds unlike segments, the first of each is refined further, from the bytes around its anchor.
   A bucket of up to ``FEW`` unlike segments compares them in pairs, which tells at once which strings are equal. A
   larger one is refined by blocks of ``BLOCK`` neighbouring strings, and where blocks are unlike still, string by string;
   identifiers of longer stretches before and after the anchor are built from those of shorter ones.

Scale. Work on single bytes is in array operations over about ``_SLICE`` bytes, which fit a core's cache. Each step
aggregates before it shuffles; text meets its (few) places twice, by document id. A bucket that a third of all segments are
in is dealt over many tasks (``salted_join``), a segment that often goes by broadcast, as does a bucket of so many unlike
segments (``hot_join``). Nothing is collected.

Edge cases. Null and empty texts have 0 bytes and no removal; texts under ``least`` bytes lose nothing; very long texts are
read in overlapping slices. An empty table gives an empty table. Only the id and text columns are read, so further columns
may have any names. Ids must tell texts apart: rows repeated with their id are one document and each gets its result. A null
id stands before all others. Segments are told apart by their bucket (64 bits) and two identifiers of all their bytes (96
bits), strings by 128 bits; unlike segments of a small bucket are compared byte by byte.
"""

from __future__ import annotations

from functools import lru_cache

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from .common import _M1, _M2, GOLD, col, drop_written, hot_join, mix64, salted_join, small_batches, written

#: Bytes of a first bucket; unlike segments of a bucket up to which they are compared in pairs; strings of a block.
Q, FEW, BLOCK = 16, 64, 8
_SLICE = 1 << 17
_PLACE = np.uint64((1 << 24) - 1)
_SEEDS = (np.uint64(0x2545F4914F6CDD1D), np.uint64(0xD6E8FEB86659FD93))
#: Odd factors of the sums that name stretches; 5 more than a multiple of 8, so that their powers differ in low bits too.
_BASES = (np.uint64(0x9FB21C651E98DF25), np.uint64(0xC2B2AE3D27D4EB4D))
_FIRST = -(1 << 63)


def _words(a: np.ndarray) -> np.ndarray:
    """The 8 bytes from each place on."""
    return np.ndarray((len(a) - 7,), "<u8", np.ascontiguousarray(a), 0, (1,)).astype(np.uint64)


def _mixed(h: np.ndarray) -> np.ndarray:
    """``mix64`` in place."""
    for shift, by in ((30, _M1), (27, _M2)):
        h ^= h >> np.uint64(shift)
        h *= by
    h ^= h >> np.uint64(31)
    return h


def _buckets(v: np.ndarray, seed: np.uint64) -> np.ndarray:
    """Identifier of the Q bytes from each place on, from the 8 bytes there."""
    out = v >> np.uint64(29)
    out ^= v
    out *= seed
    one = v[:-8] ^ seed
    one *= GOLD
    one += out[8:]
    return _mixed(one)


@lru_cache(maxsize=8)
def _powers(size: int, base: int) -> np.ndarray:
    out = np.full(size, base, np.uint64)
    out[0] = 1
    return np.cumprod(out, dtype=np.uint64)


def _stretches(v: np.ndarray, base: np.uint64, low: np.ndarray, high: np.ndarray) -> np.ndarray:
    """Identifiers of v[low:high], wherever that stands: the difference of two sums of terms times powers of an odd base."""
    size = 1 << len(v).bit_length()
    sums = np.zeros(len(v) + 1, np.uint64)
    np.cumsum(v * _powers(size, int(base))[: len(v)], out=sums[1:])
    return (sums[high] - sums[low]) * _powers(size, pow(int(base), -1, 1 << 64))[low]


def _segments(a: np.ndarray, starts: np.ndarray, ends: np.ndarray, least: int, whole: bool = True) -> tuple[np.ndarray, ...]:
    """(bucket, two identifiers, document, place, further strings, anchor's offset) of the segments of several texts laid
    end to end; without ``whole`` their buckets only."""
    v = _words(a)
    bucket = _buckets(v, _SEEDS[0])
    w = least - Q + 1
    n = len(bucket)
    key = bucket & ~_PLACE
    key |= np.arange(n, dtype=np.uint64)
    # The least of w neighbours, from those of 1, 2, 4, ... neighbours.
    width = 1
    while width < w:
        step = min(width, w - width)
        key = np.minimum(key[:-step], key[step:])
        width += step
    key &= _PLACE
    valid = np.zeros(len(key) + 2, np.int32)
    long = ends - starts >= least
    np.add.at(valid, starts[long] + 1, 1)
    np.add.at(valid, ends[long] - least + 2, -1)
    # One place without a string before and after the others.
    ok = np.r_[np.cumsum(valid[:-1]) > 0, False]
    same = np.r_[False, key[1:] == key[:-1], False]
    same &= ok[1:]
    same &= ok[:-1]
    first = np.flatnonzero(ok[1:-1] & ~same[:-1])
    anchor = key[first].astype(np.int64)
    if not whole:
        return (bucket[anchor],)
    # Two texts may meet in one stretch only through a gap, as the last strings of a text are no valid places.
    last = np.flatnonzero(ok[1:-1] & ~same[1:])
    doc = np.searchsorted(starts, first, side="right") - 1
    # The second identifier comes from the 8 bytes at each place, so that both together are 96 bits of every byte.
    more = (last - first).astype(np.uint64) * _SEEDS[1]
    one = _stretches(bucket, _BASES[0], first, last + (least - Q + 1))
    v ^= v >> np.uint64(29)
    v *= _M2
    v ^= v >> np.uint64(32)
    two = _stretches(v, _BASES[1], first, last + (least - 7))
    seg = [mix64(x * GOLD + more) for x in (one, two)]
    return bucket[anchor], *seg, doc, first - starts[doc], last - first, anchor - first


def _pieces(texts: list[bytes], least: int):
    """Groups of (document, offset, bytes) of about a slice each; long texts come in slices that overlap by a string less a byte."""
    group, size = [], 0
    for i, t in enumerate(texts):
        for at in range(0, max(1, len(t) - least + 1), _SLICE):
            part = t[at : at + _SLICE + least - 1] if len(t) > _SLICE else t
            if len(part) >= least:
                group.append((i, at, part))
                size += len(part)
            if size >= _SLICE:
                yield group
                group, size = [], 0
            if len(t) <= _SLICE:
                break
    if group:
        yield group


def _laid(group: list[tuple[int, int, bytes]]) -> tuple[np.ndarray, np.ndarray, np.ndarray]:
    """The texts of a group end to end, their starts and ends."""
    lengths = np.array([len(g[2]) for g in group])
    ends = np.cumsum(lengths)
    return np.frombuffer(b"".join(g[2] for g in group), np.uint8), ends - lengths, ends


def _texts(b: pa.RecordBatch) -> list[bytes]:
    return [t or b"" for t in b.column(1).cast(pa.binary()).to_pylist()]


def _anchor_buckets(least: int):
    def run(batches):
        for b in batches:
            for group in _pieces(_texts(b), least):
                (h,) = _segments(*_laid(group), least, whole=False)
                yield pa.RecordBatch.from_arrays([pa.array(h.view(np.int64))], names=["h"])

    return run


def _anchors(least: int):
    def run(batches):
        for b in batches:
            ids = b.column(0).to_numpy(zero_copy_only=False)
            for group in _pieces(_texts(b), least):
                h, g, g2, doc, place, more, off = _segments(*_laid(group), least)
                own, offset = np.array([x[0] for x in group]), np.array([x[1] for x in group], np.int64)
                yield pa.RecordBatch.from_arrays(
                    [pa.array(h.view(np.int64)), pa.array(g.view(np.int64)), pa.array((g2 >> np.uint64(32)).astype(np.uint32).view(np.int32)), pa.array(ids[own[doc]]), pa.array((place + offset[doc]).astype(np.int64) << 20 | more << 10 | off)],
                    names=["h", "g", "g2", "i", "k"],
                )

    return run


#: What refinement needs of a segment: its strings' offsets (of the anchor at x) and the bytes on either side.
_PARTS = "h long, i long, x long, lo int, hi int, before binary, after binary, many boolean"


def _listed(column: pa.Array) -> tuple[pa.StructArray, np.ndarray]:
    """The structs of a column of lists, null lists being empty, and the row that each stands in."""
    size = np.asarray(column.value_lengths().fill_null(0)).astype(np.int64)
    return column.flatten(), np.repeat(np.arange(len(size)), size)


def _numbers(column: pa.StructArray, name: str) -> np.ndarray:
    return column.field(name).to_numpy(zero_copy_only=False).astype(np.int64)


def _rows(column: pa.Array, side: int) -> np.ndarray:
    """The byte strings of ``side`` bytes each of a column."""
    if not len(column):
        return np.zeros((0, side), np.uint8)
    column = column.cast(pa.binary())
    at = int(np.frombuffer(column.buffers()[1], np.int32)[column.offset])
    return np.frombuffer(column.buffers()[2], np.uint8)[at : at + len(column) * side].reshape(-1, side)


def _strip(rows: np.ndarray) -> pa.Array:
    """A column of the rows' byte strings."""
    offsets = np.arange(0, (len(rows) + 1) * rows.shape[1], rows.shape[1], dtype=np.int32)
    return pa.Array.from_buffers(pa.binary(), len(rows), [None, pa.py_buffer(offsets), pa.py_buffer(np.ascontiguousarray(rows))])


def _parts(least: int):
    side = least - Q
    names = ["h", "i", "x", "lo", "hi", "before", "after", "many"]

    def run(batches):
        for b in batches:
            z, row = _listed(b.column(2))
            texts = _texts(b)
            # Texts lie end to end with ``least`` zero bytes before and after each.
            gap = b"\0" * least
            laid = np.frombuffer(gap + gap.join(texts) + gap, np.uint8)
            length = np.array([len(t) for t in texts], np.int64)
            begin = np.cumsum(length + least) - length
            i = b.column(0).to_numpy(zero_copy_only=False).astype(np.int64)
            h, s, off, more = (_numbers(z, c) for c in ("h", "s", "off", "more"))
            many = z.field("many")
            around = np.lib.stride_tricks.sliding_window_view(laid, side)
            for k in range(0, len(row), 20_000):
                p = slice(k, k + 20_000)
                x = s[p] + off[p]
                at = begin[row[p]] + x
                columns = [h[p], i[row[p]], x, (off[p] - more[p]).astype(np.int32), off[p].astype(np.int32)]
                yield pa.RecordBatch.from_arrays([*map(pa.array, columns), _strip(around[at - side][:, ::-1]), _strip(around[at + Q]), many[k : k + 20_000]], names=names)

    return run


def _grown(sides: np.ndarray, seed: np.uint64) -> np.ndarray:
    """Identifiers of the first 0, 1, 2, ... bytes of every row, each from the one before."""
    out = np.empty((sides.shape[1] + 1, len(sides)), np.uint64)
    out[0] = seed
    for k in range(sides.shape[1]):
        out[k + 1] = mix64(out[k] * GOLD + sides[:, k].astype(np.uint64) + seed)
    return out


class _Sides:
    """Segments of a batch (h, i, x, lo, hi, before, after) and identifiers of their stretches."""

    def __init__(self, b: pa.RecordBatch, least: int):
        self.side = least - Q
        self.h, self.i, self.x, self.lo, self.hi = (np.asarray(b.column(c).to_numpy(zero_copy_only=False)).astype(np.int64) for c in ("h", "i", "x", "lo", "hi"))
        before, after = (_rows(b.column(c), self.side) for c in ("before", "after"))
        self.ids = [(_grown(before, seed), _grown(after, seed)) for seed in _SEEDS]

    def names(self, at: np.ndarray, low: np.ndarray, high: np.ndarray) -> list[np.ndarray]:
        """Both identifiers of the strings with the anchor at offsets low to high, of the segments ``at``."""
        return [mix64(mix64(left[high, at] * GOLD + right[self.side - low, at]) * GOLD + self.h[at].view(np.uint64) + (low * 1024 + high).astype(np.uint64)).view(np.int64) for left, right in self.ids]


def _blocks(least: int):
    """(c, b, w1, w2, i, x, s, e): the blocks of strings of each segment; c names the bytes that all strings of a block share."""

    def run(batches):
        for b in batches:
            z = _Sides(b, least)
            for k in range((least - Q) // BLOCK + 1):
                first, last = k * BLOCK, min(k * BLOCK + BLOCK - 1, least - Q)
                low, high = np.maximum(z.lo, first), np.minimum(z.hi, last)
                at = np.flatnonzero(high >= low)
                low, high = low[at], high[at]
                core = z.names(at, np.full(len(at), last), np.full(len(at), first))[0]
                yield pa.RecordBatch.from_arrays([pa.array(c) for c in (core, np.full(len(at), k, np.int32), *z.names(at, low, high), z.i[at], z.x[at], z.x[at] - high, z.x[at] - low + least)], names=["c", "b", "w1", "w2", "i", "x", "s", "e"])

    return run


def _strings(least: int):
    """(w1, w2, i, s): the strings of the listed blocks (last column) of each segment."""

    def run(batches):
        for b in batches:
            z = _Sides(b, least)
            listed = b.column("blocks").to_pylist()
            at = np.array([n for n, ks in enumerate(listed) for _ in ks], np.int64)
            first = np.array([k * BLOCK for ks in listed for k in ks], np.int64)
            for d in range(BLOCK):
                o = first + d
                ok = (o >= z.lo[at]) & (o <= z.hi[at])
                yield pa.RecordBatch.from_arrays([pa.array(c) for c in (*z.names(at[ok], o[ok], o[ok]), z.i[at[ok]], z.x[at[ok]] - o[ok])], names=["w1", "w2", "i", "s"])

    return run


def _agree(a: np.ndarray, b: np.ndarray) -> np.ndarray:
    """Length of the common start of the rows."""
    same = a == b
    return np.where(same.all(axis=1), same.shape[1], np.argmin(same, axis=1))


def _compared(least: int):
    """Removed stretches (i, s, e) from the pairs of unlike segments of each bucket, the later of a pair losing."""
    side = least - Q

    def pairs(i, x, lo, hi, before, after, one, two):
        low = np.maximum(side - _agree(after[one], after[two]), np.maximum(lo[one], lo[two]))
        high = np.minimum(_agree(before[one], before[two]), np.minimum(hi[one], hi[two]))
        ok = high >= low
        at = x[two][ok]
        return i[two][ok], at - high[ok], at - low[ok] + least

    def run(batches):
        for b in batches:
            z, row = _listed(b.column(0))
            if not len(row):
                continue
            i, x_, lo, hi = (_numbers(z, c) for c in ("i", "x", "lo", "hi"))
            order = np.lexsort((x_, i, row))
            i, x_, lo, hi = i[order], x_[order], lo[order], hi[order]
            before, after = (_rows(z.field(c), side)[order] for c in ("before", "after"))
            size = np.bincount(row)
            size = size[size > 0]
            begin = np.cumsum(size) - size
            shape = {n: np.triu_indices(n, 1) for n in set(size.tolist())}
            one = np.concatenate([shape[n][0] + at for n, at in zip(size.tolist(), begin.tolist())])
            two = np.concatenate([shape[n][1] + at for n, at in zip(size.tolist(), begin.tolist())])
            for k in range(0, len(one), 50_000):
                got = pairs(i, x_, lo, hi, before, after, one[k : k + 50_000], two[k : k + 50_000])
                yield pa.RecordBatch.from_arrays([pa.array(x) for x in got], names=["i", "s", "e"])

    return run


def _cut(batches):
    for b in batches:
        texts = _texts(b)
        size = np.array([len(t) for t in texts], np.int64)
        ends = np.cumsum(size)
        z, row = _listed(b.column(2))
        s, e = (_numbers(z, c) + (ends - size)[row] for c in ("s", "e"))
        order = np.lexsort((s, row))
        row, s, e = row[order], s[order], np.maximum.accumulate(e[order])
        # A run goes on where the next place starts within it or at its end, but not into the next text.
        new = np.ones(len(s) + 1, bool)
        new[1:-1] = (s[1:] > e[:-1]) | (row[1:] != row[:-1])
        row, s, e = row[new[:-1]], s[new[:-1]], e[new[1:]]
        spans, removed = np.bincount(row, minlength=len(size)), np.zeros(len(size), np.int64)
        np.add.at(removed, row, e - s)
        data = memoryview(b"".join(texts))
        left = b"".join(data[x:y] for x, y in zip([0, *e.tolist()], [*s.tolist(), len(data)]))
        offsets = np.r_[0, np.cumsum(size - removed)].astype(np.int32)
        kept = pa.Array.from_buffers(pa.binary(), len(size), [None, pa.py_buffer(offsets), pa.py_buffer(left)])
        yield pa.RecordBatch.from_arrays([b.column(0), pa.array(size), pa.array(removed), pa.array(spans), kept], names=["i", "n_bytes", "n_removed", "n_spans", "kept"])


def dedup_substrings(spark: SparkSession, docs: DataFrame, id_col: str = "doc_id", text_col: str = "text", least: int = 100) -> DataFrame:
    """Per document: ``id_col``, n_bytes, n_removed, n_spans (maximal removed runs) and kept (the remaining bytes)."""
    if not 2 * Q <= least <= 1000:
        raise ValueError(f"least must be {2 * Q} to 1000 bytes")
    small_batches(spark)
    d = docs.select(F.coalesce(col(id_col).cast("long"), F.lit(_FIRST)).alias("i"), col(text_col).cast("string").alias("t"))
    # A segment's place, further strings and anchor's offset go as one number, in the order of places.
    # Of unique text it is cheaper to read the anchors twice than to write them.
    anchors = d.mapInArrow(_anchors(least), "h long, g long, g2 int, i long, k long")
    again = written(spark, d.mapInArrow(_anchor_buckets(least), "h long").groupBy("h").agg(F.count("*").alias("n")).where("n > 1"), "again")
    live = written(spark, salted_join(anchors, again, ["h"], "n", ["i", "k"]).drop("n"), "segments")
    place, more, off = F.shiftright("k", 20), F.shiftright("k", 10).bitwiseAND(F.lit(1023)).cast("int"), F.col("k").bitwiseAND(F.lit(1023)).cast("int")
    alike = written(spark, live.groupBy("h", "g", "g2").agg(F.min(F.struct("i", "k")).alias("first"), F.count("*").alias("n")), "classes")
    copied = written(spark, alike.where("n > 1").select("h", "g", "g2", "first", "n"), "copied")
    whole = hot_join(live, copied, ["h", "g", "g2"], "n").where(F.col("first") < F.struct("i", "k")).select("i", place.alias("s"), (place + more + least).alias("e"))
    whole = written(spark, whole.groupBy("i").agg(F.collect_list(F.struct("s", "e")).alias("places")), "whole")
    unlike = written(spark, alike.groupBy("h").agg(F.count("*").alias("c")).where("c > 1"), "unlike")
    todo = hot_join(alike, unlike, ["h"], "c").select("h", (F.col("c") > FEW).alias("many"), "first.i", "first.k").groupBy("i").agg(F.collect_list(F.struct(place.alias("s"), more.alias("more"), off.alias("off"), "h", "many")).alias("segments"))
    parts = written(spark, d.join(todo, "i").select("i", "t", "segments").mapInArrow(_parts(least), _PARTS), "parts")
    few = parts.where("NOT many").groupBy("h").agg(F.collect_list(F.struct("i", "x", "lo", "hi", "before", "after")).alias("x"))
    few = few.select("x").mapInArrow(_compared(least), "i long, s long, e long")
    many = parts.where("many").drop("many")
    blocks = written(spark, many.mapInArrow(_blocks(least), "c long, b int, w1 long, w2 long, i long, x long, s long, e long"), "blocks")
    named = written(spark, blocks.groupBy("c", "b", "w1", "w2").agg(F.min(F.struct("i", "x")).alias("first"), F.count("*").alias("n")), "block_classes")
    later = blocks.join(named.where("n > 1").select("w1", "w2", "first"), ["w1", "w2"]).where(F.col("first") < F.struct("i", "x")).select("i", "s", "e")
    # Strings of two blocks can be equal only where what all strings of a block share is.
    still = named.join(named.groupBy("c", "b").agg(F.count("*").alias("m")).where("m > 1").select("c", "b"), ["c", "b"])
    still = still.select("first.i", "first.x", "b").groupBy("i", "x").agg(F.collect_list("b").alias("blocks"))
    strings = written(spark, many.join(still, ["i", "x"]).mapInArrow(_strings(least), "w1 long, w2 long, i long, s long"), "strings")
    first = strings.groupBy("w1", "w2").agg(F.min(F.struct("i", "s")).alias("first"), F.count("*").alias("n")).where("n > 1").drop("n")
    single = strings.join(first, ["w1", "w2"]).where(F.col("first") < F.struct("i", "s")).select("i", "s", (F.col("s") + least).alias("e"))
    cut = few.unionByName(later).unionByName(single).groupBy("i").agg(F.collect_list(F.struct("s", "e")).alias("places"))
    gone = written(spark, whole.unionByName(cut).groupBy("i").agg(F.flatten(F.collect_list("places")).alias("places")), "places")
    drop_written(spark, again, copied, live, alike, unlike, parts, whole, blocks, named, strings)
    out = d.join(gone, "i", "left").select("i", "t", "places").mapInArrow(_cut, "i long, n_bytes long, n_removed long, n_spans long, kept binary")
    return out.select(F.when(F.col("i") != _FIRST, F.col("i")).alias(id_col), "n_bytes", "n_removed", "n_spans", "kept")
