"""Secrets: base patterns, and a battery of randomness tests with length-aware false-discovery control.

Method. Three base patterns (assignments, access keys, long hexadecimal runs) give base spans; the value of each is put to
the battery. So is every maximal run of at least ``LEAST`` encoding characters outside base spans that is not a word by its
shape (letters of one case, or with a capital in front). A token's encoding is inferred from its characters (decimal,
hexadecimal, base 32, base 36, base 62 or base 64), its characters become numbers of that alphabet, and three tests ask whether
the numbers are uniform and independent: chi-squared over the alphabet, runs above and below the middle, and serial
correlation at lag one. The least of the three p-values, times three, is the token's. Within each band of length a step-up
rule at level ``LEVEL`` decides which tokens are declared regular; of the others, those of under ``BITS`` bits for their
alphabet are too short to tell, and the rest are random. A random run outside base spans is added as kind ``random``; base
spans stay whatever the battery says, and it is reported for each.

Places follow from lengths: a text split at its matches gives the characters between them, so a running sum over both has
every match's start and end, in blocks, so that texts full of matches take no longer for it. All is built-in functions.

Scale. The text is scanned once; only spans, tokens and counts of (band of length, binned p-value) leave the scan.

Edge cases. Null counts as empty text: no spans, the hash of the empty string. Very long texts are scanned whole. An empty
table gives an empty table. Repeated rows are scanned alike and each counts in the bands. Only the id and text columns are
read, so further columns may have any names. Spans are code points with the end exclusive; runs within a base span are no
tokens of their own.
"""

from __future__ import annotations

from pyspark.sql import Column, DataFrame, SparkSession
from pyspark.sql import functions as F
from pyspark.sql.window import Window

from .common import col, written

#: Base kinds in the order of ties: pattern, its group for the least length, the least length (fixed values).
BASE = (
    ("assign", r"""(?i:(password|passwd|secret|token|api_?key))["']?\x20*[:=]\x20*["']?([A-Za-z0-9+/_.=-]+)""", 2, 6),
    ("access", r"AKIA[A-Z0-9]+", 0, 20),
    ("hex", r"[0-9a-f]+", 0, 24),
)
#: Shortest run; bits that a random token has at least; level of the step-up rule; bins of a p-value (twenty to a power of ten).
LEAST, BITS, LEVEL, BINS = 16, 80, 0.05, 400
#: What a run of letters looks like that is a word.
WORDLIKE = r"^([A-Z]?[a-z]+|[A-Z]+)$"
CANDIDATE = rf"(?<![A-Za-z0-9+/_-])[A-Za-z0-9+/_-]{{{LEAST},}}={{0,2}}"
#: Encodings by what their tokens look like: pattern and alphabet; the first that fits is inferred (fixed values).
ENCODINGS = (
    (r"^[0-9]+$", "0123456789"),
    (r"^[0-9a-f]+$", "0123456789abcdef"),
    (r"^[0-9A-F]+$", "0123456789ABCDEF"),
    (r"^[A-Z2-7]+$", "ABCDEFGHIJKLMNOPQRSTUVWXYZ234567"),
    (r"^[a-z0-9]+$", "0123456789abcdefghijklmnopqrstuvwxyz"),
    (r"^[A-Z0-9]+$", "0123456789ABCDEFGHIJKLMNOPQRSTUVWXYZ"),
    (r"^[A-Za-z0-9]+$", "0123456789ABCDEFGHIJKLMNOPQRSTUVWXYZabcdefghijklmnopqrstuvwxyz"),
    (r"", "ABCDEFGHIJKLMNOPQRSTUVWXYZabcdefghijklmnopqrstuvwxyz0123456789+/-_"),
)


#: Matches of a block of the running sum.
_BLOCK = 256
_SPANS = "array<struct<s: int, o: int, kind: string, e: int, token: string>>"


def _placed(d: DataFrame, kind: str, order: int, pattern: str, token: str) -> DataFrame:
    """Column ``kind``, the matches of ``pattern`` in ``t``, replaced by their spans; ``token`` is SQL for the token of match k."""
    step = f"transform(zip_with(slice(split(t, {_quoted(pattern)}, -1), 1, size(`{kind}`)), `{kind}`, (a, b) -> char_length(a) + char_length(b)), x -> x)"
    d = d.withColumn("step", F.expr(f"CASE WHEN size(`{kind}`) > 0 THEN {step} END"))
    block = f"aggregate(slice(step, cast(b * {_BLOCK} + 1 AS INT), {_BLOCK}), cast(array() AS array<int>), (acc, y) -> concat(acc, array(coalesce(get(acc, size(acc) - 1), 0) + y)))"
    d = d.withColumn("within", F.expr(f"CASE WHEN step IS NOT NULL THEN transform(sequence(0, cast((size(step) - 1) div {_BLOCK} AS INT)), b -> {block}) END"))
    d = d.withColumn("before", F.expr("CASE WHEN step IS NOT NULL THEN aggregate(within, named_struct('s', 0, 'o', cast(array() AS array<int>)), (acc, w) -> named_struct('s', acc.s + get(w, size(w) - 1), 'o', concat(acc.o, array(acc.s))), acc -> acc.o) END"))
    ends = "flatten(zip_with(within, before, (w, o) -> transform(w, v -> v + o)))"
    span = f"named_struct('s', e - char_length(get(`{kind}`, k)), 'o', {order}, 'kind', '{kind}', 'e', e, 'token', {token})"
    return d.withColumn("placed", F.expr(f"CASE WHEN step IS NOT NULL THEN transform({ends}, (e, k) -> {span}) ELSE cast(array() AS {_SPANS}) END")).drop("step", "within", "before", kind).withColumnRenamed("placed", kind)


def _quoted(text: str) -> str:
    return "'" + text.replace("\\", "\\\\").replace("'", "\\'") + "'"


def spans(docs: DataFrame, text_col: str = "text", keep: tuple[str, ...] = ("doc_id",)) -> DataFrame:
    """Columns ``keep`` with the base spans by kind and the spans ``random`` of other runs, each with its token."""
    d = docs.select(*[col(k) for k in keep], F.coalesce(col(text_col).cast("string"), F.lit("")).alias("t"))
    for i, (kind, pattern, group, least) in enumerate(BASE):
        # Every assignment is walked over, even one that is too short; runs of [0-9a-f] are too many for that, and can't overlap.
        whole = pattern if group else pattern[:-1] + "{" + str(24 if kind == "hex" else 16) + ",}"
        d = d.withColumn(kind, F.regexp_extract_all("t", F.lit(whole), F.lit(0)))
        if group:
            d = d.withColumn("value", F.when(F.size(kind) > 0, F.regexp_extract_all("t", F.lit(whole), F.lit(group))).otherwise(F.array()))
        d = _placed(d, kind, i, whole, "get(value, k)" if group else f"get(`{kind}`, k)")
        d = d.withColumn(kind, F.filter(kind, lambda x: F.length(x["token"]) >= least)) if group else d
    d = d.withColumn("random", F.regexp_extract_all("t", F.lit(CANDIDATE), F.lit(0)))
    d = _placed(d, "random", len(BASE), CANDIDATE, "get(`random`, k)").withColumn("random", F.filter("random", lambda x: ~x["token"].rlike(WORDLIKE)))
    return d.select(*[col(k) for k in keep], *[k for k, *_ in BASE], "random")


def _upper_tail(z: Column) -> Column:
    """Upper tail of the normal distribution (a published five-term approximation; its constants are fixed values)."""
    x = F.abs(z)
    t = 1 / (1 + 0.2316419 * x)
    poly = t * (0.319381530 + t * (-0.356563782 + t * (1.781477937 + t * (-1.821255978 + t * 1.330274429))))
    tail = F.exp(-x * x / 2) * 0.3989422804014327 * poly
    return F.when(z >= 0, tail).otherwise(1 - tail)


def battery(tokens: DataFrame, token_col: str = "token") -> DataFrame:
    """``tokens`` with alphabet size, n, the three p-values and p (three times the least, at most 1)."""
    bare = F.regexp_replace(F.col(token_col), "=+$", "")
    alphabet = F.lit(ENCODINGS[-1][1])
    for pattern, letters in reversed(ENCODINGS[:-1]):
        alphabet = F.when(bare.rlike(pattern), F.lit(letters)).otherwise(alphabet)
    d = tokens.withColumns({"b": bare, "letters": alphabet})
    d = d.withColumns({"n": F.length("b").cast("double"), "k": F.length("letters").cast("double"), "v": F.expr("transform(split(b, ''), c -> cast(instr(letters, c) - 1 AS double))"), "c": F.expr("transform(array_distinct(split(b, '')), c -> pow(char_length(b) - char_length(replace(b, c, '')), 2))")})
    d = d.withColumns({"sq": F.expr("aggregate(c, 0D, (a, x) -> a + x)"), "mean": F.expr("aggregate(v, 0D, (a, x) -> a + x) / n"), "up": F.expr("transform(v, x -> CASE WHEN x >= k / 2 THEN 1 ELSE 0 END)")})
    d = d.withColumns(
        {
            "n1": F.expr("cast(aggregate(up, 0, (a, x) -> a + x) AS double)"),
            "turns": F.expr("1D + aggregate(zip_with(slice(up, 1, size(up) - 1), slice(up, 2, size(up) - 1), (a, x) -> CASE WHEN a <> x THEN 1 ELSE 0 END), 0, (a, x) -> a + x)"),
            "var": F.expr("aggregate(v, 0D, (a, x) -> a + (x - mean) * (x - mean))"),
            "cov": F.expr("aggregate(zip_with(slice(v, 1, size(v) - 1), slice(v, 2, size(v) - 1), (a, x) -> (a - mean) * (x - mean)), 0D, (a, x) -> a + x)"),
        }
    )
    n, n1, n0 = F.col("n"), F.col("n1"), F.col("n") - F.col("n1")
    chi = F.col("sq") * F.col("k") / n - n
    z_chi = (chi - (F.col("k") - 1)) / F.sqrt(2 * (F.col("k") - 1) * (n - 1) / n)
    expected = 1 + 2 * n1 * n0 / n
    spread = 2 * n1 * n0 * (2 * n1 * n0 - n) / (n * n * (n - 1))
    z_runs = F.when(spread > 0, (F.col("turns") - expected) / F.sqrt(spread)).otherwise(F.lit(9.0))
    z_serial = F.when(F.col("var") > 0, (F.col("cov") / F.col("var") + 1 / n) * F.sqrt(n)).otherwise(F.lit(9.0))
    d = d.withColumns({"p_chi": _upper_tail(z_chi), "p_runs": 2 * _upper_tail(F.abs(z_runs)), "p_serial": 2 * _upper_tail(F.abs(z_serial))})
    d = d.withColumn("p", F.least(F.lit(1.0), 3 * F.least("p_chi", "p_runs", "p_serial")))
    return d.drop("b", "letters", "v", "c", "sq", "mean", "up", "n1", "turns", "var", "cov")


def judged(tested: DataFrame, level: float = LEVEL) -> DataFrame:
    """``tested`` with ``verdict``: 'regular' by the step-up rule within bands of length, 'short' if too short to tell, or 'random'.

    p-values are binned, each standing for the upper edge of its bin, so that the rule errs towards keeping.
    """
    t = tested.withColumns({"band": F.least(F.lit(12), F.floor(F.log2(F.greatest("n", F.lit(1.0))) * 2)).cast("int"), "bin": F.least(F.lit(BINS), F.floor(-20 * F.log10(F.greatest("p", F.lit(1e-30))))).cast("int")})
    counts = t.groupBy("band", "bin").count()
    order = Window.partitionBy("band").orderBy(F.desc("bin"))
    counts = counts.withColumns({"below": F.sum("count").over(order), "all": F.sum("count").over(Window.partitionBy("band"))})
    edge = F.pow(F.lit(10.0), -F.col("bin") / 20)
    cut = counts.where(edge <= F.lit(level) * F.col("below") / F.col("all")).groupBy("band").agg(F.min("bin").alias("cut"))
    # Bands are a dozen rows.
    t = t.join(F.broadcast(cut), "band", "left")
    verdict = F.when(F.col("cut").isNotNull() & (F.col("bin") >= F.col("cut")), "regular").when(F.col("n") * F.log2("k") < BITS, "short").otherwise("random")
    return t.withColumn("verdict", verdict).drop("band", "bin", "cut")


def undisproved(tested: DataFrame, level: float = LEVEL) -> DataFrame:
    """Rows of ``tested`` that are random as far as can be told."""
    return judged(tested, level).where("verdict = 'random'").drop("verdict")


def scan(spark: SparkSession, docs: DataFrame, id_col: str = "doc_id", text_col: str = "text") -> DataFrame:
    """Per document: ``id_col``, and arrays of spans (s, o, kind, e): assign, access, hex, random, base and all in order; and
    ``tested``, what the battery says of every token: (s, o, kind, e, p, verdict) of base values and of other runs."""
    found = written(spark, spans(docs, text_col, (id_col,)).withColumn("row", F.monotonically_increasing_id()), "spans")
    base = F.concat("assign", "access", "hex")
    outside = F.filter("random", lambda r: ~F.exists(base, lambda b: (b["s"] <= r["s"]) & (b["e"] >= r["e"])))
    each = found.select("row", F.explode(F.concat(base, outside)).alias("f")).select("row", "f.*")
    tested = written(spark, battery(each), "tested")
    verdicts = judged(tested).groupBy("row").agg(F.sort_array(F.collect_list(F.struct("s", "o", "kind", "e", F.round("p", 4).alias("p"), "verdict"))).alias("tested"))
    out = found.drop("random").join(verdicts, "row", "left")
    out = out.withColumn("tested", F.coalesce("tested", F.expr("cast(array() AS array<struct<s: int, o: int, kind: string, e: int, p: double, verdict: string>>)")))

    def bare(spans_: Column) -> Column:
        return F.transform(spans_, lambda x: F.struct(x["s"].alias("s"), x["o"].alias("o"), x["kind"].alias("kind"), x["e"].alias("e")))

    random = bare(F.filter("tested", lambda x: (x["kind"] == "random") & (x["verdict"] == "random")))
    out = out.withColumn("random", random)
    kinds = [bare(F.col(k)).alias(k) for k, *_ in BASE]
    return out.select(col(id_col), *kinds, "random", F.sort_array(bare(base)).alias("base"), F.sort_array(F.concat(bare(base), "random")).alias("all"), "tested")


def verdicts(column: str = "tested") -> Column:
    """What the battery says as kind:start:end:p:verdict, comma-joined in the order of places."""
    return F.array_join(F.transform(column, lambda x: F.concat_ws(":", x["kind"], x["s"].cast("string"), x["e"].cast("string"), x["p"].cast("string"), x["verdict"])), ",")


def joined(column: str) -> Column:
    """Spans as kind:start:end, comma-joined in their order."""
    return F.array_join(F.transform(F.col(column), lambda x: F.concat_ws(":", x["kind"], x["s"].cast("string"), x["e"].cast("string"))), ",")
