"""Quality rules: a decision list learned by sequential covering, applied as ordered Spark conditions.

Method. Statistics of each whole text are computed with built-in functions and written once as a narrow table. On
labelled rows a list of rules for low quality is grown: each rule starts empty and takes on the threshold condition of
the highest information gain until it covers no good document or has ``MOST`` conditions; then conditions are pruned
from its end as long as that does not lower its worth on rows set aside. A rule is kept if it is precise enough; what
it covers is removed, and the next is grown. The list is emitted as one ``CASE WHEN`` expression.

The learner reads a sample bounded by ``SAMPLE`` expected labelled rows (numbers only, drawn by a hash of the id).

Edge cases. Null text counts as empty: no words, so it fails the base rule. Very long texts are measured whole. Rows without
a label do not train; a document labelled twice takes the lower label; without labels the list is empty and only the base
rule decides. Conditions of equal gain: the statistic listed first, its lower cut. Repeated rows are judged alike. An empty
table gives an empty table. Only the id and text columns are read, so further columns may have any names.
"""

from __future__ import annotations

from dataclasses import dataclass, field

import numpy as np
from pyspark.sql import Column, DataFrame, SparkSession
from pyspark.sql import functions as F

from .common import WORD, written

#: Expected labelled rows read; candidate cuts of a statistic; conditions of a rule; least precision; least share of rows a rule covers.
SAMPLE, CUTS, MOST, PRECISE, COVERS = 20_000, 48, 3, 0.9, 0.002
_BLANKS = " \t\n\u000b\f\r"
#: Statistics that rules may test, all ratios or counts that do not grow with the corpus.
STATISTICS = ("n_words", "mean_word", "symbol_share", "dup_line_share", "repeat_share", "upper_share", "digit_share", "bang_share", "distinct_share", "stop_line_share")


def statistics(docs: DataFrame, text_col: str = "text", keep: tuple[str, ...] = ("doc_id",)) -> DataFrame:
    """Columns ``keep`` with word_chars, n_words, n_symbols, n_dup_lines, n_repeat_words and the tested shares."""
    text = F.coalesce(F.col(text_col).cast("string"), F.lit(""))
    d = docs.select(*keep, text.alias("t"))
    lines = F.filter(F.split("t", "\n", -1), lambda x: x.rlike(WORD))
    d = d.select(*keep, "t", F.regexp_extract_all("t", F.lit(WORD), F.lit(0)).alias("w"), lines.alias("lines"))
    d = d.withColumns({"n_words": F.size("w").cast("long"), "n_lines": F.size("lines").cast("long")})
    # A window is named by a hash of its three words; equal ones meet when names are sorted with their places.
    window = F.expr("CASE WHEN n_words < 3 THEN array() ELSE transform(sequence(0, cast(n_words - 3 AS INT)), i -> xxhash64(w[i], w[i + 1], w[i + 2])) END")
    d = d.withColumn("h", window)
    d = d.withColumn("s", F.expr("CASE WHEN size(h) = size(array_distinct(h)) THEN NULL ELSE sort_array(transform(h, (x, i) -> named_struct('h', x, 'i', i))) END"))
    d = d.withColumn("at", F.expr("CASE WHEN s IS NULL THEN NULL ELSE flatten(zip_with(slice(s, 1, size(s) - 1), slice(s, 2, size(s) - 1), (a, b) -> CASE WHEN a.h = b.h THEN array(a.i, b.i) ELSE array() END)) END"))
    repeated = F.expr("CASE WHEN s IS NULL THEN 0 ELSE size(array_distinct(flatten(transform(at, i -> array(i, i + 1, i + 2))))) END").cast("long")

    def without(letters: str) -> Column:
        return F.length("t") - F.length(F.translate("t", letters, ""))

    d = d.select(
        *keep,
        "n_words",
        F.length(F.translate("t", _BLANKS, "")).cast("long").alias("word_chars"),
        without("#*$%&|<>").cast("long").alias("n_symbols"),
        (F.col("n_lines") - F.size(F.array_distinct("lines"))).cast("long").alias("n_dup_lines"),
        repeated.alias("n_repeat_words"),
        "n_lines",
        without("ABCDEFGHIJKLMNOPQRSTUVWXYZ").alias("n_upper"),
        without("0123456789").alias("n_digits"),
        without("!?").alias("n_bangs"),
        F.size(F.array_distinct("w")).alias("n_distinct"),
        F.size(F.filter("lines", lambda x: F.rtrim(x).rlike(r"[.!?:;\"')\]]$"))).alias("n_stop_lines"),
    )

    def share(a: str, b: str) -> Column:
        return F.when(F.col(b) > 0, F.col(a) / F.col(b)).otherwise(F.lit(0.0))

    return d.select(
        *keep, "word_chars", "n_words", "n_symbols", "n_dup_lines", "n_repeat_words",
        share("word_chars", "n_words").alias("mean_word"), share("n_symbols", "word_chars").alias("symbol_share"), share("n_dup_lines", "n_lines").alias("dup_line_share"),
        share("n_repeat_words", "n_words").alias("repeat_share"), share("n_upper", "word_chars").alias("upper_share"), share("n_digits", "word_chars").alias("digit_share"),
        share("n_bangs", "word_chars").alias("bang_share"), share("n_distinct", "n_words").alias("distinct_share"), share("n_stop_lines", "n_lines").alias("stop_line_share"),
    )


#: The base rule: too few words, or more than half of the words inside repeated three-word windows.
BASE_FAILED = "n_words < 50 OR 100 * n_repeat_words > 50 * n_words"


@dataclass(frozen=True)
class Condition:
    name: str
    above: bool  # at or above the cut, else under it
    cut: float

    def sql(self) -> str:
        return f"{self.name} {'>=' if self.above else '<'} {self.cut!r}D"

    def holds(self, x: dict[str, np.ndarray]) -> np.ndarray:
        return x[self.name] >= self.cut if self.above else x[self.name] < self.cut


@dataclass
class DecisionList:
    """Ordered rules of conjoined conditions for low quality; what none covers is kept."""

    rules: list[tuple[Condition, ...]] = field(default_factory=list)

    def sql(self) -> str:
        """1-based number of the first rule that holds, else 0."""
        cases = " ".join(f"WHEN {' AND '.join(c.sql() for c in rule)} THEN {i}" for i, rule in enumerate(self.rules, 1))
        return f"CASE {cases} ELSE 0 END" if self.rules else "0"

    def column(self) -> Column:
        return F.expr(self.sql())


def _gain(p: np.ndarray, n: np.ndarray, p0: float, n0: float) -> np.ndarray:
    """Information gain of narrowing (p0, n0) low and good rows to (p, n), as in rule induction by covering."""
    with np.errstate(divide="ignore", invalid="ignore"):
        return np.where(p > 0, p * (np.log2(p / np.maximum(p + n, 1)) - np.log2(p0 / (p0 + n0))), -1.0)


def learn(x: dict[str, np.ndarray], low: np.ndarray, aside: np.ndarray, statistics: tuple[str, ...] = STATISTICS) -> DecisionList:
    """Sequential covering over columns ``x``; rows ``aside`` prune rules, the others grow them."""
    rules: list[tuple[Condition, ...]] = []
    left = np.ones(len(low), bool)
    cuts = {c: np.unique(np.quantile(x[c], np.linspace(0, 1, CUTS + 1)[1:-1])) for c in statistics} if len(low) else {}

    def counts(at: np.ndarray) -> tuple[int, int]:
        return int((at & low).sum()), int((at & ~low).sum())

    while (left & low).any():
        at, rule = left & ~aside, []
        while len(rule) < MOST:
            p0, n0 = counts(at)
            if not p0 or not n0:
                break
            best = (0.0, None)
            for c in statistics:
                values, labels = x[c][at], low[at]
                place = np.searchsorted(cuts[c], values, side="right")
                p, n = (np.bincount(place[m], minlength=len(cuts[c]) + 1) for m in (labels, ~labels))
                under_p, under_n = np.cumsum(p)[:-1].astype(float), np.cumsum(n)[:-1].astype(float)
                for above, a, b in ((False, under_p, under_n), (True, p0 - under_p, n0 - under_n)):
                    g = _gain(a, b, p0, n0)
                    if len(g) and g.max() > best[0] + 1e-9:
                        best = (float(g.max()), Condition(c, above, float(cuts[c][int(g.argmax())])))
            if best[1] is None:
                break
            rule.append(best[1])
            at = at & best[1].holds(x)
        if not rule:
            break

        def worth(part: list[Condition]) -> float:
            on = left & aside
            for c in part:
                on = on & c.holds(x)
            p, n = counts(on)
            return (p - n) / (p + n) if p + n else -1.0

        while len(rule) > 1 and worth(rule[:-1]) >= worth(rule):
            rule.pop()
        on = left.copy()
        for c in rule:
            on &= c.holds(x)
        p, n = counts(on)
        if p + n < max(4, COVERS * len(low)) or p < PRECISE * (p + n):
            break
        rules.append(tuple(rule))
        left &= ~on
    return DecisionList(rules)


def fit(stats: DataFrame, labels: DataFrame, id_col: str = "doc_id", label_col: str = "quality", sample: int = SAMPLE, seed: int = 3) -> DecisionList:
    """Learn from rows of ``stats`` whose label (1 good, 0 low) is known and that pass the base rule."""
    known = labels.where(F.col(label_col).isNotNull()).groupBy(id_col).agg(F.min(label_col).cast("int").alias("_good"))
    n = known.count()
    if not n:
        return DecisionList()
    u = F.pmod(F.xxhash64(F.lit(seed), id_col), F.lit(1 << 30))
    drawn = known.where(u < F.lit(int(min(1.0, sample / n) * (1 << 30))))
    rows = stats.join(drawn, id_col).where(f"NOT ({BASE_FAILED})").select("_good", u.alias("_u"), *STATISTICS).orderBy("_u").collect()
    x = {c: np.array([float(r[c]) for r in rows]) for c in STATISTICS}
    return learn(x, np.array([r["_good"] == 0 for r in rows], bool), np.arange(len(rows)) % 3 == 2)


def judge(spark: SparkSession, docs: DataFrame, labels: DataFrame, id_col: str = "doc_id", text_col: str = "text") -> DataFrame:
    """Per document: its statistics, base_failed, rule (number of the rule that rejects it, 0 for none) and kept."""
    stats = written(spark, statistics(docs, text_col, (id_col,)), "statistics")
    rule = fit(stats, labels, id_col).column()
    out = stats.withColumns({"base_failed": F.expr(BASE_FAILED), "rule": rule})
    return out.withColumn("kept", ~F.col("base_failed") & (F.col("rule") == 0))
