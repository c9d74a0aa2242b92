"""Document fingerprints from spot signatures.

Method. Every common word (an anchor) together with the next two content words after it is a spot; a document's
fingerprint is the set of its spots, hashed to 32 bits and sorted. Documents are compared by the Jaccard likeness of
these sets. For a threshold, sets are partitioned by size, so that only those meet whose sizes do not rule it out, and within
a partition on as many of their rarest spots as a partner may lack, and one more; what meets is compared. ``near_classes``
finds the components of near fingerprints in this way, ``near_pairs`` the pairs.

A text without a spot falls back to adjacent word pairs, then to its only word, so that any two texts with a word can
be told apart; the empty set is that of texts without words, and two empty sets are alike (likeness 1).

Scale. ``with_next`` puts each document beside the next one by descending id with one shuffle of the texts: ranges of
ids, bounded by approximate quantiles, are buckets; the first document of a bucket also goes to the one before it. Frequent
spots come last in the order that says which of a set's spots are posted, so a passage that a third of all documents share
is posted only by documents that hold little else; these are linked through one of them.

Edge cases. Null counts as empty text. Rows of equal id follow each other in the order of a hash of their texts. A null
id comes after all others. A single document is its own next; an empty table gives an empty table. Very long texts have large
sets, compared whole. Only the id and text columns are read, so further columns may have any names. Everything is built-in
functions. Two spots may share a 32-bit hash: a set of a thousand has such a pair with a chance of one in ten thousand.
"""

from __future__ import annotations

import math

from pyspark.sql import Column, DataFrame, SparkSession
from pyspark.sql import functions as F
from pyspark.sql.window import Window

from .common import col, connected_components, drop_written, hot_join, written

#: Common words of English, German, French and Spanish that serve as anchors (fixed values).
ANCHORS = tuple(
    """a an and are as at be been but by can do for from had has have he her his i if in is it its not of on or our she so
    that the their them there they this to was we were what when which who will with would you
    als am auch auf aus bei bin bis das dass dem den der des die durch ein eine einem einen einer es für haben hat ich im
    ist kann mit nach nicht noch nur oder sich sie sind so über um und von vor war wie wir wird zu zum zur
    au aux avec ce ces cette dans de des du elle en est et il ils je la le les leur mais ne nous on ou par pas plus pour
    qu que qui sa se ses son sont sur un une vous
    al con como de del el ella en era es esta este fue ha las lo los más me mi muy no o para pero por que se si sin su sus
    te tiene una uno y ya yo""".split()
)
_FIRST = -(1 << 63)
#: Classes (expected) of which the frequency of spots is estimated, and the most frequent spots that come last in the order.
SAMPLE, LAST = 20_000, 500
#: Lists in which two classes must meet to be compared, for likenesses over 0.75; one list for lower ones.
MEET = 3
#: Words of 64 bits in which every spot of a set sets one bit: so many that sets of up to a thousand spots leave half of them empty.
WORDS = 16


def fingerprint(text: Column) -> Column:
    """The sorted distinct spot hashes of a text column (array of int).

    The text is laid out as pieces, each a content word with the anchors that follow it, so the anchors of piece j
    stand before content words j and j + 1 (counted from the piece's own, which is j - 1).
    """
    words = F.regexp_extract_all(F.lower(F.coalesce(text, F.lit(""))), F.lit(r"[\p{L}\p{M}\p{N}]+"), F.lit(0))
    anchor = list(dict.fromkeys(ANCHORS))

    def spots(w: Column) -> Column:
        marked = F.array_join(F.transform(w, lambda x: F.when(x.isin(anchor), F.concat(x, F.lit(" "))).otherwise(F.concat(F.lit("\u0002"), x, F.lit("\u0003")))), "")
        content = F.filter(w, lambda x: ~x.isin(anchor))
        # One element each, so that a lambda's parameter stands for a computed array.
        return F.transform(
            F.array(F.struct(F.split(marked, "\u0002").alias("p"), content.alias("c"))),
            lambda z: F.flatten(
                F.transform(
                    F.slice(z["p"], 1, F.greatest(F.lit(0), F.size(z["c"]) - 1)),
                    lambda piece, j: F.transform(F.filter(F.split(F.substring_index(piece, "\u0003", -1), " "), lambda a: a != ""), lambda a: F.hash(a, F.get(z["c"], j), F.get(z["c"], j + 1))),
                )
            ),
        )[0]

    def pairs(w: Column) -> Column:
        return F.when(F.size(w) > 1, F.transform(F.slice(w, 2, F.greatest(F.lit(1), F.size(w) - 1)), lambda x, i: F.hash(F.get(w, i), x))).otherwise(F.transform(w, lambda x: F.hash(x)))

    def full(w: Column) -> Column:
        return F.transform(F.array(F.struct(w.alias("w"), spots(w).alias("s"))), lambda z: F.when(F.size(z["s"]) > 0, z["s"]).otherwise(pairs(z["w"])))[0]

    return F.sort_array(F.array_distinct(F.transform(F.array(words), full)[0]))


def printed(sets: Column) -> Column:
    """A fingerprint as text: its hashes in order, separated by blanks."""
    return F.array_join(F.transform(sets, lambda x: x.cast("string")), " ")


def likeness(a: Column, b: Column, least: float = 0.0) -> Column:
    """Jaccard likeness of two fingerprints; 0 where their sizes alone keep it under ``least``."""
    low, high = F.least(F.size(a), F.size(b)), F.greatest(F.size(a), F.size(b))
    both = F.size(F.array_intersect(a, b))
    value = both / (F.size(a) + F.size(b) - both)
    return F.when(high == 0, F.lit(1.0)).when(low < least * high - 1e-9, F.lit(0.0)).otherwise(value).cast("double")


def with_next(docs: DataFrame, id_col: str = "doc_id", text_col: str = "text", per_bucket: int = 1000, most_buckets: int = 20_000) -> DataFrame:
    """(i, t, n, s) of each document and (next_t, next_s) of the next by descending id; s is the fingerprint."""
    d = docs.select(col(id_col).alias("id"), F.coalesce(col(id_col).cast("long"), F.lit(_FIRST)).alias("i"), F.coalesce(col(text_col).cast("string"), F.lit("")).alias("t"))
    ids = d.select("i")
    n = ids.count()
    k = max(1, min(most_buckets, n // per_bucket))
    bounds = ids.agg(F.percentile_approx("i", [j / k for j in range(1, k)], 10 * k)).first()[0] if n and k > 1 else []
    bounds = sorted(set(bounds or []))
    if bounds:
        # Binary search in the sorted bounds: how many are at most the id.
        steps = len(bounds).bit_length()
        search = f"""aggregate(sequence(1, {steps}), named_struct('lo', 0, 'hi', {len(bounds)}),
          (r, x) -> CASE WHEN r.lo >= r.hi THEN r WHEN bounds[(r.lo + r.hi) div 2] <= i THEN named_struct('lo', cast((r.lo + r.hi) div 2 + 1 AS INT), 'hi', r.hi)
                    ELSE named_struct('lo', r.lo, 'hi', cast((r.lo + r.hi) div 2 AS INT)) END, r -> r.lo)"""
        bucket = F.expr(search.replace("bounds", f"array({', '.join(f'{b}L' for b in bounds)})".replace("-9223372036854775808L", "cast('-9223372036854775808' AS BIGINT)")))
    else:
        bucket = F.lit(0)
    # One row a bucket: its largest id, which stands next after the bucket above.
    tops = {r["b"]: r["top"] for r in ids.select(bucket.alias("b"), "i").groupBy("b").agg(F.max("i").alias("top")).collect()}
    order = sorted(tops)
    above = {b: order[(p + 1) % len(order)] for p, b in enumerate(order)}
    if order:
        size = order[-1] + 1
        top = F.lit([tops.get(b) for b in range(size)]).cast("array<bigint>")
        to = F.lit([above.get(b, 0) for b in range(size)]).cast("array<int>")
        d = d.withColumn("b", bucket)
        copies = F.when(F.col("i") == F.get(top, F.col("b")), F.array(F.struct(F.col("b").alias("b"), F.lit(0).alias("g")), F.struct(F.get(to, F.col("b")).alias("b"), F.lit(1).alias("g")))).otherwise(F.array(F.struct(F.col("b").alias("b"), F.lit(0).alias("g"))))
        d = d.select("id", "i", "t", F.explode(copies).alias("x")).select("id", "i", "t", "x.b", "x.g")
    else:
        d = d.withColumns({"b": F.lit(0), "g": F.lit(0)})
    d = d.repartition("b").withColumn("s", fingerprint(F.col("t")))
    after = Window.partitionBy("b").orderBy("g", F.desc("i"), F.xxhash64("t"))
    d = d.withColumns({"next_t": F.lead("t").over(after), "next_s": F.lead("s").over(after)}).where("g = 0")
    return d.select(F.col("id").alias(id_col), "t", F.length("t").cast("long").alias("n"), "s", "next_t", "next_s")


def edited(n: str = "n", text: str = "t", following: str = "next_t") -> Column:
    """The text with its last third (rounded down, in code points) replaced by as much of the start of the next text."""
    k = F.floor(F.col(n) / 3).cast("int")
    return F.concat(F.substring(F.col(text), F.lit(1), (F.col(n) - k).cast("int")), F.substring(F.col(following), F.lit(1), k))


def band(n: Column, least: float) -> Column:
    """Partition of a set size: sets of bands further apart than one differ too much in size to be ``least`` alike."""
    return F.floor(F.log(n.cast("double")) / F.lit(-math.log(least)) + F.lit(1e-9)).cast("int")


def _meet(least: float) -> int:
    return MEET if least > 0.75 else 1


def _posted(classes: DataFrame, least: float) -> DataFrame:
    """(x, part, c, n, home): each class under its rarest spots, in the partition of its size (home) and the next one up.

    Two sets ``least`` alike share ``meet`` spots among the first n - ceil(least * n) + ``meet`` of each, in any one order of
    spots. The order here is by hash, with the spots last that are most frequent in a sample: what the sample says makes lists
    short or long but loses nothing. A set too small for so many shared spots is like no other than itself.
    """
    meet = _meet(least)
    drawn = classes.where(F.pmod(F.xxhash64("c"), F.lit(1 << 20)) < F.lit(float(1 << 20) * SAMPLE / max(1, classes.count())))
    often = drawn.select(F.explode("s").alias("x")).groupBy("x").agg(F.count("*").alias("df")).where("df > 2").orderBy(F.desc("df"), "x").limit(LAST).collect()
    last = F.array(*[F.lit(r["x"]) for r in reversed(often)]).cast("array<int>")
    need = (F.col("n") - F.ceil(F.lit(least) * F.col("n") - 1e-9) + meet).cast("int")
    first = F.slice(F.concat(F.array_except("s", last), F.array_intersect(last, "s")), F.lit(1), need)
    post = classes.where((F.lit(meet) == 1) | (F.col("n") > meet)).select("c", "n", F.explode(first).alias("x")).withColumn("b", band(F.col("n"), least))
    part = F.explode(F.array(F.struct(F.col("b").alias("part"), F.lit(True).alias("home")), F.struct((F.col("b") + 1).alias("part"), F.lit(False).alias("home"))))
    return post.withColumn("p", part).select("x", "p.part", "c", "n", "p.home")


def _bits(s: Column) -> list[Column]:
    """The words w0, w1, ... in which every spot of a set sets one of ``64 * WORDS`` bits."""
    one = F.lit(1).cast("bigint")

    def word(k: int) -> Column:
        mine = F.filter(s, lambda x: F.shiftrightunsigned(x, 6).bitwiseAND(F.lit(WORDS - 1)) == k)
        return F.aggregate(mine, F.lit(0).cast("bigint"), lambda a, x: a.bitwiseOR(F.call_function("shiftleft", one, x.bitwiseAND(F.lit(63)))))

    return [word(k).alias(f"w{k}") for k in range(WORDS)]


def near_classes(spark: SparkSession, docs: DataFrame, least: float = 0.8) -> DataFrame:
    """(f1, f2, near_id) of fingerprints ``docs`` (doc_id, s, f1, f2: two hashes of s): the least id of its component, where
    fingerprints at least ``least`` alike are linked.

    Equal fingerprints are one class. Lists of a spot and a partition of sizes are worked off twice: each class with the least
    of its list, which is linear, then what lies in other components than most of its list. Pairs that meet in enough lists
    are compared. A pair that is in one component already can join nothing, so no link is lost.
    """
    least_id = F.min(F.coalesce(F.col("doc_id").cast("long"), F.lit(_FIRST)))
    classes = written(spark, docs.groupBy("f1", "f2").agg(least_id.alias("c"), F.max("s").alias("s")).withColumn("n", F.size("s")), "classes")
    sets = classes.where("n > 0").select("c", "n", "s")
    posted = written(spark, _posted(sets, least), "posted")
    lists = posted.groupBy("x", "part").agg(F.count("*").alias("m"), F.min(F.when(F.col("home"), F.col("c"))).alias("pivot")).where("m > 1 AND pivot IS NOT NULL")
    lists = written(spark, lists, "lists")
    joined = written(spark, hot_join(posted, lists, ["x", "part"], "m").drop("m"), "joined")
    drop_written(spark, posted, lists)

    def near(pairs: DataFrame) -> DataFrame:
        """The pairs (one row for each list they met in) that are alike."""
        met = pairs.groupBy("a", "b").agg(F.count("*").alias("met")).where(F.col("met") >= _meet(least))
        one = sets.select(F.col("c").alias("a"), F.col("s").alias("sa"))
        two = sets.select(F.col("c").alias("b"), F.col("s").alias("sb"))
        return met.join(one, "a").join(two, "b").where(likeness(F.col("sa"), F.col("sb"), least) >= least).select("a", "b")

    fits = f"least({{0}}, {{1}}) >= {least} * greatest({{0}}, {{1}}) - 1e-9"
    links = written(spark, near(joined.where("pivot <> c").select(F.col("pivot").alias("a"), F.col("c").alias("b"))), "links")
    comp = written(spark, connected_components(spark, links).select(F.col("node").alias("c"), "component"), "components")
    words = sets.select("c", *_bits(F.col("s"))).join(comp, "c", "left")
    placed = joined.join(words, "c").withColumn("component", F.coalesce("component", "c"))
    split = placed.groupBy("x", "part").agg(F.min("component").alias("c0"), F.max("component").alias("c1")).where("c0 <> c1").select("x", "part")
    placed = written(spark, placed.join(split, ["x", "part"]).drop("pivot"), "placed")
    drop_written(spark, joined)
    main = placed.groupBy("x", "part", "component").count().groupBy("x", "part").agg(F.max_by("component", F.struct("count", "component")).alias("main"))
    placed = placed.join(main, ["x", "part"]).withColumn("rest", F.col("component") != F.col("main")).drop("main")
    apart = f"u.x = v.x AND u.part = v.part AND u.component <> v.component AND (NOT v.rest OR u.c < v.c) AND (u.home OR v.home) AND {fits.format('u.n', 'v.n')}"
    # A bit that one of two sets has alone is a spot that it has alone, and alike sets have few of these.
    differ = " + ".join(f"bit_count(u.w{k} ^ v.w{k})" for k in range(WORDS))
    apart += f" AND {differ} <= {(1 - least) / (1 + least)} * (u.n + v.n) + 1e-9"
    pairs = placed.where("rest").alias("u").join(placed.alias("v"), F.expr(apart)).select(F.least("u.c", "v.c").alias("a"), F.greatest("u.c", "v.c").alias("b"))
    every = written(spark, links.unionByName(near(pairs)), "links")
    comp = written(spark, connected_components(spark, every).select(F.col("node").alias("c"), "component"), "components")
    found = classes.select("f1", "f2", "c").join(comp, "c", "left").withColumn("near_id", F.coalesce("component", "c"))
    return found.select("f1", "f2", F.when(F.col("near_id") != _FIRST, F.col("near_id")).alias("near_id"))


def near_pairs(docs: DataFrame, least: float = 0.8, id_col: str = "doc_id", text_col: str = "text") -> DataFrame:
    """(a, b, likeness) of distinct fingerprints at least ``least`` alike, by their smallest ids: all pairs, for a search over
    groups of which none is large; ``near_classes`` is for any."""
    sets = docs.select(col(id_col).alias("i"), fingerprint(col(text_col)).alias("s")).where("size(s) > 0")
    classes = sets.groupBy("s").agg(F.min("i").alias("c")).withColumn("n", F.size("s"))
    posted = _posted(classes, least)
    a, b = posted.alias("a"), posted.alias("b")
    fits = f"a.x = b.x AND a.part = b.part AND (a.home OR b.home) AND a.c < b.c AND least(a.n, b.n) >= {least} * greatest(a.n, b.n) - 1e-9"
    met = a.join(b, F.expr(fits)).groupBy(F.col("a.c").alias("a"), F.col("b.c").alias("b")).agg(F.count("*").alias("met"))
    pairs = met.where(F.col("met") >= _meet(least)).drop("met")
    one, two = classes.select(F.col("c").alias("a"), F.col("s").alias("sa")), classes.select(F.col("c").alias("b"), F.col("s").alias("sb"))
    return pairs.join(one, "a").join(two, "b").select("a", "b", likeness(F.col("sa"), F.col("sb"), least).alias("likeness")).where(F.col("likeness") >= least)
