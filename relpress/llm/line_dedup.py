"""Line deduplication: repeated runs of lines, found by prefix doubling over line-ID sequences.

Method. A document is its sequence of lines that have a word; a line's ID is the name of its class of equal lines. A
suffix of a sequence is ranked by its first line, then by its first 2, 4, ... lines: the rank of 2k lines is the name of
the pair (rank of the first k, rank of the next k), until no two suffixes agree any more. A class with one member can
have no repeated prefix of that length or more, so it leaves after its round, and the rounds run over what repeats only.
Suffixes of one class share a prefix of at least that length, an interval of the longest-common-prefix table; a repeated
run of any length is covered by the two classes of the greatest power of two within it, so the union of a document's
overlapping intervals is its maximal repeated runs.

A run counts from ``min_words`` words on, and every line of a later copy of one is deleted; of equal runs the first in
(document, line) order stays. A line that goes lies in a copied run of at most ``min_words`` lines with that many words
or in a longer one, so besides the powers of two the lengths up to ``min_words`` are looked at: such a run is the overlap
of two ranks.

Scale. Text is read twice (to name its lines, and to delete); between, only narrow rows of lines are shuffled, with
partial aggregation, so a line that stands in a third of all documents is one row a task before the shuffle; its class
name goes back to its places by broadcast (``hot_join``). Rounds number the doublings of the longest repeated run.

Edge cases. Null text counts as empty: one line, nothing removed. Lines without a word are never removed and do not
interrupt a run. Rows of the same id and text are one document and each get its result; a null id is one id, before all
others. A very long text is many lines; the window over its lines is one sort of narrow rows. An empty table gives an
empty table. Further columns, of any names, come back as they were.
"""

from __future__ import annotations

from pyspark.sql import Column, DataFrame, SparkSession
from pyspark.sql import functions as F
from pyspark.sql.window import Window

from .common import WORD, col, drop_written, free_name, hot_join, written

#: Least words of a repeated run that is deleted.
MIN_WORDS = 5
_FIRST = -(1 << 63)


def _key(docs: DataFrame, id_col: str, text_col: str) -> DataFrame:
    """(row, i, t, h): the document's columns in a struct of their own, so that no name of theirs can clash."""
    text = F.coalesce(col(text_col).cast("string"), F.lit(""))
    d = docs.select(F.struct(*[col(c) for c in docs.columns]).alias("row"), F.coalesce(col(id_col).cast("long"), F.lit(_FIRST)).alias("i"), text.alias("t"))
    return d.withColumn("h", F.xxhash64("t"))


def _need(words: str, at: str, least: int) -> str:
    """SQL for the number of lines from ``at`` on that first reach ``least`` words; null if the text ends before."""
    total, cases = f"{words}[{at}]", []
    for n in range(1, least + 1):
        cases.append(f"WHEN {at} + {n} <= size({words}) AND {total} >= {least} THEN {n}")
        total += f" + coalesce(get({words}, {at} + {n}), 0)"
    return f"CASE {' '.join(cases)} END"


def lines_of(docs: DataFrame, id_col: str = "doc_id", text_col: str = "text", min_words: int = MIN_WORDS) -> DataFrame:
    """(i, h, q, pos, a, b, need): the lines that have a word, by document key, with two hashes and the least run from there."""
    d = _key(docs, id_col, text_col).select("i", "h", F.filter(F.transform(F.split("t", "\n", -1), lambda x, p: F.struct(p.alias("p"), x.alias("x"), F.regexp_count(x, F.lit(WORD)).alias("w"))), lambda z: z["w"] > 0).alias("z"))
    d = d.withColumn("w", F.transform("z", lambda z: z["w"]))
    d = d.select("i", "h", F.posexplode(F.expr(f"transform(z, (y, n) -> named_struct('p', y.p, 'a', xxhash64(y.x), 'b', xxhash64(7, y.x), 'need', {_need('w', 'n', min_words)}))")).alias("q", "y"))
    return d.select("i", "h", "q", F.col("y.p").alias("pos"), F.col("y.a").alias("a"), F.col("y.b").alias("b"), F.col("y.need").alias("need"))


def _classes(spark: SparkSession, rows: DataFrame, by: list[str], name: str) -> DataFrame:
    """Rows of classes with at least two members, with ``first``, the least (i, h, q) of the class, as its name."""
    named = written(spark, rows.groupBy(*by).agg(F.count("*").alias("members"), F.min(F.struct("i", "h", "q")).alias("first")).where("members > 1"), f"classes_{name}")
    return hot_join(rows, named, by, "members").drop(*by, "members")


def later_copies(spark: SparkSession, docs: DataFrame, id_col: str = "doc_id", text_col: str = "text", min_words: int = MIN_WORDS) -> DataFrame:
    """(i, h, q, n): n lines from line q of document (i, h) on stand earlier as well and have the words of a run.

    Of a line only the longest such stretch is given. The stretches of a document overlap; their union is its runs.
    """
    rows = written(spark, lines_of(docs, id_col, text_col, min_words), "lines")
    here = F.struct("i", "h", "q")
    ranked, depth, found, old = _classes(spark, rows, ["a", "b"], "lines"), 1, [], [rows]
    while True:
        ranked = written(spark, ranked.select("i", "h", "q", "need", F.col("first").alias("rank")), f"rank{depth}")
        old.append(ranked)
        if ranked.isEmpty():
            break
        found.append(ranked.where((F.col("need") <= depth) & (F.col("rank") < here)).select("i", "h", "q", F.lit(depth).alias("n")))
        order = Window.partitionBy("i", "h").orderBy("q")

        def ahead(n: int, rank: str = "rank") -> Column:
            """The rank n lines further on, where that line is still in the run."""
            return F.when(F.lead("q", n).over(order) == F.col("q") + n, F.lead(rank, n).over(order))

        # Rows of one line number repeat where equal documents do; one of them stands for all.
        single = ranked.repartition("i", "h").dropDuplicates(["i", "h", "q"])
        # Runs between two powers that may have just the words of a run: the overlap of two ranks of the lower depth.
        between = [n for n in range(depth + 1, min(2 * depth, min_words + 1))]
        if between:
            pairs = single.withColumn("others", F.array(*[F.struct(F.lit(n).alias("n"), ahead(n - depth).alias("rank")) for n in between]))
            pairs = pairs.withColumn("other", F.explode("others"))
            pairs = pairs.where(F.col("other.rank").isNotNull() & (F.col("need") <= F.col("other.n")))
            pairs = written(spark, pairs.select("i", "h", "q", "rank", F.col("other.rank").alias("other"), F.col("other.n").alias("n")), "between")
            old.append(pairs)
            both = _classes(spark, pairs.withColumn("length", F.col("n")), ["rank", "other", "length"], "between")
            found.append(both.where(F.col("first") < here).select("i", "h", "q", "n"))
        pairs = written(spark, single.withColumn("other", ahead(depth)).where(F.col("other").isNotNull()), f"pairs{depth}")
        old.append(pairs)
        ranked, depth = _classes(spark, pairs, ["rank", "other"], f"{2 * depth}"), 2 * depth
    out = found[0] if found else ranked.select("i", "h", "q", F.lit(0).alias("n"))
    for f in found[1:]:
        out = out.unionByName(f)
    out = written(spark, out.groupBy("i", "h", "q").agg(F.max("n").alias("n")), "copies")
    drop_written(spark, *old)
    return out


def maximal_runs(copies: DataFrame) -> DataFrame:
    """(i, h, runs): the union of each document's stretches as its maximal runs, (from, to) line numbers in order, ends exclusive."""
    order = Window.partitionBy("i", "h").orderBy("q")
    reach = F.max(F.col("q") + F.col("n")).over(order.rowsBetween(Window.unboundedPreceding, -1))
    marked = copies.withColumn("opens", (F.col("q") > F.coalesce(reach, F.lit(-1))).cast("int")).withColumn("run", F.sum("opens").over(order))
    runs = marked.groupBy("i", "h", "run").agg(F.min("q").alias("from"), F.max(F.col("q") + F.col("n")).alias("to"))
    return runs.groupBy("i", "h").agg(F.array_sort(F.collect_list(F.struct("from", "to"))).alias("runs"))


def dedup_lines(spark: SparkSession, docs: DataFrame, id_col: str = "doc_id", text_col: str = "text", min_words: int = MIN_WORDS) -> DataFrame:
    """``docs`` with ``text_col`` less its later copies, and n_lines, n_removed, n_runs (maximal removed runs).

    Where ``docs`` has columns of these names, theirs stay and the measures get underscores in front.
    """
    runs = maximal_runs(later_copies(spark, docs, id_col, text_col, min_words))
    none = F.expr("cast(array() AS array<struct<from: int, to: int>>)")
    d = _key(docs, id_col, text_col).join(runs, ["i", "h"], "left").withColumn("runs", F.coalesce("runs", none))
    d = d.withColumn("gone", F.flatten(F.transform("runs", lambda r: F.sequence(r["from"], r["to"] - 1))))

    def kept_of(z: Column) -> Column:
        """The text of lines z.l less those that go: z.g has their numbers among the lines that have a word."""
        real = F.filter(F.transform(z["l"], lambda x, n: F.when(x.rlike(WORD), n)), lambda n: n.isNotNull())
        # One element each, so that a lambda's parameter stands for the computed array, which is then computed once.
        gone = F.transform(F.array(real), lambda r: F.transform(z["g"], lambda q: F.get(r, q)))[0]
        rest = F.array_except(F.sequence(F.lit(0), F.size(z["l"]) - 1), gone)
        return F.array_join(F.transform(rest, lambda n: F.get(z["l"], n)), "\n")

    both = F.array(F.struct(F.split("t", "\n", -1).alias("l"), F.col("gone").alias("g")))
    kept = F.when(F.size("gone") == 0, F.col("t")).otherwise(F.transform(both, kept_of)[0])
    return d.select(
        *[(kept if c == text_col else F.col("row").getField(c)).alias(c) for c in docs.columns],
        F.size(F.split("t", "\n", -1)).cast("long").alias(free_name(docs, "n_lines")),
        F.size("gone").cast("long").alias(free_name(docs, "n_removed")),
        F.size("runs").cast("long").alias(free_name(docs, "n_runs")),
    )


def oracle(min_words: int = MIN_WORDS, table: str = "documents") -> str:
    """CTEs in DuckDB SQL up to ``line_dedup(doc_id, n_lines, n_removed, n_runs, kept)``, for unique ids.

    Straight from the definition: equal lines of two places on one diagonal and next to each other are a common run.
    """
    word = r"[^\x20\x09-\x0D]+"
    return f"""
    ld_split AS (SELECT doc_id, string_split(coalesce(text, ''), chr(10)) AS ls FROM {table}),
    ld_all AS (SELECT doc_id, unnest(ls) AS line, unnest(range(len(ls))) AS pos FROM ld_split),
    ld_words AS (SELECT *, len(regexp_extract_all(line, '{word}')) AS w FROM ld_all),
    ld_seq AS (SELECT *, row_number() OVER (PARTITION BY doc_id ORDER BY pos) AS q FROM ld_words WHERE w > 0),
    ld_pair AS (SELECT a.doc_id AS first_id, b.doc_id, b.q - a.q AS apart, b.q, b.w FROM ld_seq a JOIN ld_seq b ON a.line = b.line AND (a.doc_id < b.doc_id OR (a.doc_id = b.doc_id AND a.q < b.q))),
    ld_run AS (SELECT *, q - row_number() OVER (PARTITION BY first_id, doc_id, apart ORDER BY q) AS run FROM ld_pair),
    ld_common AS (SELECT doc_id, q, sum(w) OVER (PARTITION BY first_id, doc_id, apart, run) AS words FROM ld_run),
    ld_gone AS (SELECT DISTINCT doc_id, q FROM ld_common WHERE words >= {min_words}),
    ld_mark AS (SELECT a.doc_id, a.pos, a.line, s.q, g.q IS NOT NULL AS gone FROM ld_all a LEFT JOIN ld_seq s USING (doc_id, pos) LEFT JOIN ld_gone g ON g.doc_id = a.doc_id AND g.q = s.q),
    ld_runs AS (SELECT doc_id, count(*) AS n_runs FROM ld_gone g WHERE NOT EXISTS (SELECT 1 FROM ld_gone x WHERE x.doc_id = g.doc_id AND x.q = g.q - 1) GROUP BY doc_id),
    line_dedup AS (
      SELECT m.doc_id, count(*) AS n_lines, CAST(count(*) FILTER (WHERE gone) AS BIGINT) AS n_removed, CAST(coalesce(any_value(n_runs), 0) AS BIGINT) AS n_runs,
        coalesce(string_agg(line, chr(10) ORDER BY pos) FILTER (WHERE NOT gone), '') AS kept
      FROM ld_mark m LEFT JOIN ld_runs r USING (doc_id) GROUP BY m.doc_id)"""
