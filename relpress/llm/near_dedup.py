"""Near-duplicate documents from bottom-k sketches of one hash function.

Method. A document's set is its distinct five-word shingles; its sketch the ``K`` smallest 64-bit hash values of that
set. Documents of equal sets form a class with one representative. Inverted lists of retained values generate
candidates, the sketch of the union estimates their likeness, and the whole sets confirm each link.

Hot values (a passage that a third of all documents share, a group of thousands of near copies) would make their lists
quadratic. Lists are therefore worked off in two passes:

1. every member is compared with its list's smallest document only, and in a long list with the one that has least of
   its own (both linear), and links are joined to components;
2. what is still apart is compared: short lists (at most ``SHORT`` members) in full; long ones between documents with
   as many hot values as the estimate asks a pair to share - a pair without a value of a short list has only hot ones
   in common, so the estimate turns down all others - but never inside one component, as such a pair can join nothing,
   nor where shingles that one document of such lists has alone already rule the likeness out.

So only the estimate can lose a link: it asks for ``SHARED`` of the union's ``K`` smallest values, which a pair of
likeness 0.85 misses with a chance of 1.4e-8, one of 0.8 with 9.2e-7.

Edge cases. Null or blank texts have the empty set and link with nothing; texts under five words have one shingle, the
whole sequence; very long texts are hashed in blocks that end at a blank. An empty table gives an empty table. Only the id and
text columns are read. Repeated rows of one doc_id give repeated result rows; a null doc_id is kept, linked with nothing.
"""

from __future__ import annotations

import hashlib

import numpy as np
import pyarrow as pa
import zstandard
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from .common import GOLD, connected_components, drop_written, mix64, small_batches, written

#: Retained values of a sketch; those of K that a pair has to share; members of a list worked off in full.
K, SHARED, SHORT = 24, 9, 64
_BLANK = np.zeros(256, bool)
_BLANK[[0x20, 9, 10, 11, 12, 13]] = True
_BASE = 0x5851F42D4C957F2D
_CHUNK = 1 << 20


class _Powers:
    """Powers of an odd base and of its inverse modulo 2**64, grown on demand."""

    up = np.ones(1, np.uint64)
    down = np.ones(1, np.uint64)

    @classmethod
    def get(cls, n: int) -> tuple[np.ndarray, np.ndarray]:
        if len(cls.up) < n:
            n = max(n, 1 << 16)
            inverse = pow(_BASE, -1, 1 << 64)
            cls.up = np.cumprod(np.r_[np.uint64(1), np.full(n, _BASE, np.uint64)])
            cls.down = np.cumprod(np.r_[np.uint64(1), np.full(n, inverse, np.uint64)])
        return cls.up, cls.down


def word_hashes(data: bytes) -> np.ndarray:
    """64-bit hashes of the blank-separated words, computed over blocks that end at a blank."""
    out, at = [], 0
    while at < len(data):
        end = min(len(data), at + _CHUNK)
        while end < len(data) and not _BLANK[data[end]]:
            end += 1
        a = np.frombuffer(data, np.uint8, end - at, at)
        up, down = _Powers.get(len(a) + 1)
        edge = np.diff(np.r_[True, _BLANK[a], True].view(np.int8))
        start, stop = np.flatnonzero(edge == -1), np.flatnonzero(edge == 1)
        total = np.zeros(len(a) + 1, np.uint64)
        np.cumsum((a.astype(np.uint64) + np.uint64(1)) * up[: len(a)], out=total[1:])
        out.append(mix64((total[stop] - total[start]) * down[start] + GOLD * (stop - start).astype(np.uint64)))
        at = end
    return np.concatenate(out) if out else np.zeros(0, np.uint64)


def shingle_set(text: str | None, words: int = 5) -> np.ndarray:
    """Sorted distinct shingle hashes of a whole text; A-Z count as a-z."""
    if not text:
        return np.zeros(0, np.uint64)
    w = word_hashes(text.encode("utf-8", "surrogatepass").lower())
    if not len(w):
        return w
    n = min(words, len(w))
    h = np.full(len(w) - n + 1, np.uint64(n), np.uint64)
    for i in range(n):
        h = mix64(h * GOLD + w[i : len(w) - n + 1 + i])
    return np.unique(h >> np.uint64(1))  # 63 bits, so that signed order is the order of values


def _sketches(words: int):
    def run(batches):
        for b in batches:
            ids, size, f1, f2, flat, offsets = b.column(0), [], [], [], [], [0]
            for t in b.column(1).to_pylist():
                s = shingle_set(t, words)
                d = np.frombuffer(hashlib.blake2b(s.tobytes(), digest_size=16).digest(), np.int64)
                size.append(len(s))
                f1.append(int(d[0]))
                f2.append(int(d[1]))
                flat.append(s[:K].view(np.int64))
                offsets.append(offsets[-1] + len(flat[-1]))
            values = np.concatenate(flat) if flat else np.zeros(0, np.int64)
            yield pa.RecordBatch.from_arrays(
                [ids, pa.array(size, pa.int64()), pa.array(f1, pa.int64()), pa.array(f2, pa.int64()), pa.ListArray.from_arrays(pa.array(offsets, pa.int32()), pa.array(values, pa.int64()))],
                names=["doc_id", "n", "f1", "f2", "sketch"],
            )

    return run


def _pack(batches):
    z = zstandard.ZstdCompressor(level=1)
    for b in batches:
        texts = [z.compress((t or "").encode("utf-8", "surrogatepass")) for t in b.column(1).to_pylist()]
        yield pa.RecordBatch.from_arrays([b.column(0), pa.array(texts, pa.binary())], names=["rep", "body"])


def _counted(words: int):
    """(s, c, rep): shingles of the documents of a task with their counts, and the least document of each."""

    def summed(sets: list[np.ndarray], reps: list[int]):
        s, r = np.concatenate(sets), np.repeat(np.array(reps, np.int64), [len(x) for x in sets])
        order = np.lexsort((r, s))
        s, r = s[order], r[order]
        first = np.flatnonzero(np.r_[True, s[1:] != s[:-1]]) if len(s) else np.zeros(0, np.int64)
        return pa.RecordBatch.from_arrays([pa.array(s[first]), pa.array(np.diff(np.r_[first, len(s)])), pa.array(r[first])], names=["s", "c", "rep"])

    def run(batches):
        unpack = zstandard.ZstdDecompressor()
        sets, reps, n = [], [], 0
        for b in batches:
            for rep, body in zip(b.column(0).to_pylist(), b.column(1)):
                sets.append(shingle_set(unpack.decompress(body.as_py()).decode("utf-8", "surrogatepass"), words).view(np.int64))
                reps.append(rep)
                n += len(sets[-1])
                if n > 1_000_000:
                    yield summed(sets, reps)
                    sets, reps, n = [], [], 0
        if sets:
            yield summed(sets, reps)

    return run


def _confirm(words: int, percent: int):
    def run(batches):
        unpack = zstandard.ZstdDecompressor()
        last, of_last = None, None
        for b in batches:
            keep = []
            a_id, a_body, b_body = b.column(0).to_pylist(), b.column(2), b.column(3)
            for i, a in enumerate(a_id):
                if a != last:
                    last, of_last = a, shingle_set(unpack.decompress(a_body[i].as_py()).decode("utf-8", "surrogatepass"), words)
                other = shingle_set(unpack.decompress(b_body[i].as_py()).decode("utf-8", "surrogatepass"), words)
                both = len(np.intersect1d(of_last, other, assume_unique=True))
                keep.append(100 * both >= percent * (len(of_last) + len(other) - both))
            yield pa.RecordBatch.from_arrays([b.column(0), b.column(1)], names=["a", "b"]).filter(pa.array(keep, pa.bool_()))

    return run


def near_components(spark: SparkSession, docs: DataFrame, id_col: str = "doc_id", text_col: str = "text", words: int = 5, percent: int = 85) -> DataFrame:
    """One row per document: ``id_col``, n_shingles, component_id (smallest reachable id), class_links (links of its class that were found)."""
    small_batches(spark)
    src = docs.select(F.col(id_col).cast("long").alias("doc_id"), F.col(text_col).alias("text"))
    sk = written(spark, src.mapInArrow(_sketches(words), "doc_id long, n long, f1 long, f2 long, sketch array<long>"), "sketches")
    classes = sk.where("n > 0 and doc_id is not null").groupBy("f1", "f2").agg(F.min("doc_id").alias("rep"), F.max("n").alias("n"), F.max("sketch").alias("sketch"))
    reps = written(spark, classes, "classes")

    posted = reps.select("rep", "n", F.explode("sketch").alias("v"))
    lists = written(spark, posted.groupBy("v").agg(F.count("*").alias("df"), F.min("rep").alias("pivot")).where("df > 1"), "lists")
    joined = written(spark, posted.join(lists, "v"), "postings")

    shared = joined.select("rep").distinct()
    bodies = written(spark, src.withColumnRenamed("doc_id", "rep").join(shared, "rep", "left_semi").select("rep", "text").mapInArrow(_pack, "rep long, body binary"), "bodies")

    def near(pairs: DataFrame) -> DataFrame:
        one = reps.select(F.col("rep").alias("a"), F.col("n").alias("na"), F.col("sketch").alias("sa"))
        two = reps.select(F.col("rep").alias("b"), F.col("n").alias("nb"), F.col("sketch").alias("sb"))
        p = pairs.join(one, "a").join(two, "b").where(f"100 * least(na, nb) >= {percent} * greatest(na, nb)")
        # The union's K smallest values are among both sketches'.
        p = p.withColumn("u", F.slice(F.array_sort(F.array_union("sa", "sb")), 1, K))
        p = p.where(K * F.size(F.array_intersect("u", F.array_intersect("sa", "sb"))) >= SHARED * F.size("u")).select("a", "b")
        full = p.join(bodies.select(F.col("rep").alias("b"), F.col("body").alias("bb")), "b").join(bodies.select(F.col("rep").alias("a"), F.col("body").alias("ab")), "a")
        return full.select("a", "b", "ab", "bb").mapInArrow(_confirm(words, percent), "a long, b long")

    # Documents whose hot values alone can pass the estimate, in their long lists. Shingles that no other such document has
    # can be in no intersection: of n values at most m = n - alone are shared, and a link needs m >= likeness * union.
    heat = joined.groupBy("rep").agg(F.sum((F.col("df") > SHORT).cast("int")).alias("hot")).join(reps.select("rep", F.size("sketch").alias("k")), "rep")
    hot = written(spark, heat.where((F.col("hot") > 0) & (K * F.col("hot") >= SHARED * F.col("k"))).select("rep"), "hot")
    crowd = bodies.join(hot, "rep", "left_semi").mapInArrow(_counted(words), "s long, c long, rep long")
    alone = crowd.groupBy("s").agg(F.sum("c").alias("c"), F.min("rep").alias("rep")).where("c = 1").groupBy("rep").agg(F.count("*").alias("alone"))
    long = joined.where(F.col("df") > SHORT).join(hot, "rep").join(alone, "rep", "left").withColumn("m", F.col("n") - F.coalesce("alone", F.lit(0))).drop("alone", "pivot")
    long = written(spark, long.where(f"100 * m >= {percent} * n"), "long")

    # First pass: with the smallest document of a list, and in long lists with the one that has least of its own.
    pivots = joined.where("pivot <> rep").select(F.col("pivot").alias("a"), F.col("rep").alias("b"))
    centre = long.groupBy("v").agg(F.min_by("rep", F.struct(1 - F.col("m") / F.col("n"), "rep")).alias("centre"))
    pivots = pivots.unionByName(long.join(centre, "v").where("centre <> rep").select(F.col("centre").alias("a"), F.col("rep").alias("b"))).distinct()
    links = written(spark, near(pivots), "links")
    comp = connected_components(spark, links)

    # Second pass: only between components. A pair of several long lists comes from the one of its least value.
    comp = written(spark, comp.select(F.col("node").alias("rep"), "component"), "first_components")

    def apart(rows: DataFrame) -> DataFrame:
        placed = rows.join(comp, "rep", "left").withColumn("component", F.coalesce("component", "rep"))
        split = placed.groupBy("v").agg(F.min("component").alias("c0"), F.max("component").alias("c1")).where("c0 <> c1").select("v")
        return placed.join(split, "v")

    short = apart(joined.where(F.col("df") <= SHORT).select("v", "rep", "n"))
    fits = f"100 * least(x.n, y.n) >= {percent} * greatest(x.n, y.n) and x.component <> y.component"
    could = f"{100 + percent} * least(x.m, y.m) >= {percent} * (x.n + y.n)"
    pairs = short.alias("x").join(short.alias("y"), F.expr(f"x.v = y.v and x.rep < y.rep and {fits}")).select(F.col("x.rep").alias("a"), F.col("y.rep").alias("b"))
    split = apart(long.select("v", "rep", "n", "m"))
    values = split.groupBy("rep").agg(F.collect_set("v").alias("vs"))  # K at most
    split = written(spark, split.join(values, "rep"), "split")
    main = split.groupBy("v", "component").count().groupBy("v").agg(F.max_by("component", F.struct("count", "component")).alias("main"))
    rest = split.join(main, "v").where("component <> main").drop("main")
    pairs = pairs.unionByName(rest.alias("x").join(split.alias("y"), F.expr(f"x.v = y.v and {fits} and {could} and x.v = array_min(array_intersect(x.vs, y.vs))")).select(F.least("x.rep", "y.rep").alias("a"), F.greatest("x.rep", "y.rep").alias("b"))).distinct()
    all_links = written(spark, links.unionByName(near(pairs)).distinct(), "all_links")
    comp = written(spark, connected_components(spark, all_links), "components")
    drop_written(spark, joined, lists, bodies, links, long, hot, split)

    degree = all_links.select(F.col("a").alias("rep")).unionByName(all_links.select(F.col("b").alias("rep"))).groupBy("rep").agg(F.count("*").alias("n_links"))
    by_class = reps.select("f1", "f2", "rep").join(comp.select(F.col("node").alias("rep"), "component"), "rep", "left").join(degree, "rep", "left")
    by_class = by_class.select("f1", "f2", F.coalesce("component", "rep").alias("component"), F.coalesce("n_links", F.lit(0)).alias("n_links"))
    real = (F.col("n") > 0) & F.col("doc_id").isNotNull()
    found = sk.drop("sketch").join(by_class, ["f1", "f2"], "left")
    return found.select(
        F.col("doc_id").alias(id_col),
        F.col("n").alias("n_shingles"),
        F.when(real, F.col("component")).otherwise(F.col("doc_id")).alias("component_id"),
        F.when(real, F.col("n_links")).otherwise(F.lit(0)).cast("long").alias("class_links"),
    )


def oracle(words: int = 5, percent: int = 85, table: str = "documents") -> str:
    """DuckDB SQL for (doc_id, n_shingles, component_id, kept), for unique ids: every pair that shares a shingle is tried."""
    upper, lower = "ABCDEFGHIJKLMNOPQRSTUVWXYZ", "abcdefghijklmnopqrstuvwxyz"
    return f"""
    WITH RECURSIVE w AS (SELECT doc_id, regexp_extract_all(translate(coalesce(text, ''), '{upper}', '{lower}'), '[^\\x20\\x09-\\x0D]+') AS ws FROM {table}),
    cut AS (SELECT doc_id, CASE WHEN len(ws) >= {words} THEN list_transform(range(1, len(ws) - {words - 2}), lambda i: array_to_string(list_slice(ws, i, i + {words - 1}), ' '))
      WHEN len(ws) > 0 THEN [array_to_string(ws, ' ')] ELSE [] END AS ss FROM w),
    sh AS (SELECT doc_id, unnest(list_distinct(ss)) AS s FROM cut),
    n AS (SELECT doc_id, len(list_distinct(ss)) AS n FROM cut),
    pairs AS (SELECT a.doc_id AS a, b.doc_id AS b, count(*) AS c FROM sh a JOIN sh b ON a.s = b.s AND a.doc_id < b.doc_id GROUP BY 1, 2),
    links AS (SELECT a, b FROM pairs JOIN n x ON x.doc_id = a JOIN n y ON y.doc_id = b WHERE 100 * c >= {percent} * (x.n + y.n - c)),
    ways AS (SELECT a, b FROM links UNION ALL SELECT b, a FROM links),
    reach AS (SELECT doc_id AS x, doc_id AS y FROM n UNION SELECT r.x, l.b FROM reach r JOIN ways l ON l.a = r.y),
    least AS (SELECT x, min(y) AS component_id FROM reach GROUP BY x)
    SELECT doc_id, CAST(n AS BIGINT) AS n_shingles, component_id, doc_id = component_id AS kept FROM n JOIN least ON x = doc_id"""
