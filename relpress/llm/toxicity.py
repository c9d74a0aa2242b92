"""Toxicity by a weighted lexicon, matched with an Aho-Corasick automaton after folding.

Method. Text is folded: compatibility forms and look-alike letters of other scripts become Latin letters, digits and
signs inside words become the letters they stand for, everything is lower case, and words are set apart by one blank.
Lexicon entries are word beginnings; their weights are log-odds between toxic and other training documents. Exception
phrases (a matched word together with the word before or after it, common in other documents) take their hit back. The
sum of weights per document is normalised by the logarithm of its length, and a logistic curve over the normalised and
the plain sum, fitted on the training documents, gives the score.

Fitting uses a sample of labelled rows bounded by ``SAMPLE`` expected documents, drawn by a hash of the id.

The lexicon holds every word beginning and every exception phrase of the sample that pass their thresholds, so the sample
bounds its size, too.

Edge cases. Null and empty texts have no hits and get the score of a document without any. Very long texts are folded in
blocks that end at a blank. Rows without a label do not train; a document labelled twice is toxic if one label says so;
without training rows the seed lexicon alone is used. Equal weights are all kept, so ties decide nothing. An empty table gives
an empty table. Repeated rows give repeated results. Only the id and text columns are read.
"""

from __future__ import annotations

import unicodedata
from collections import Counter
from collections.abc import Iterator

import ahocorasick
import numpy as np
import pandas as pd
import pyarrow as pa
import regex
from pyspark.sql import Column, DataFrame, SparkSession
from pyspark.sql import functions as F

from .common import small_batches, written

#: Expected labelled documents a fit reads; least toxic documents of an entry; least log-odds; letters of a beginning.
SAMPLE, SUPPORT, ODDS, LETTERS = 20_000, 6, 2.0, (4, 10)
#: Mild insults that are known without any label (fixed values).
SEED_WORDS = ("idiot", "moron", "stupid", "loser", "scum", "worthless", "pathetic", "trash", "clown", "disgusting")
SEED_WEIGHT = 4.0
#: Look-alike letters of other scripts, and what digits and signs stand for inside a word (fixed values).
LOOKALIKES = dict(zip("аеорсухіјѕһԁѵԛɡιοανρτκ", "aeopcyxijshdvqgioavptk"))
DIGITS = dict(zip("013457@$", "oieastas"))
_LETTER_RUN = regex.compile(r"[\p{L}\p{M}0-9@$]+")
_FOLD = str.maketrans(LOOKALIKES)
_LEET = str.maketrans(DIGITS)
_HAS_LEET = regex.compile(r"[013457@$]")
_HAS_LETTER = regex.compile(r"\p{L}")
_BLOCK = 1 << 20


def fold(text: str | None) -> Iterator[str]:
    """Folded blocks of a whole text: words between single blanks, with a blank at either end."""
    text = text or ""
    at = 0
    while at < len(text):
        end = min(len(text), at + _BLOCK)
        while end < len(text) and not text[end].isspace():
            end += 1
        block = text[at:end]
        if not block.isascii():
            block = unicodedata.normalize("NFKC", block)
        words = _LETTER_RUN.findall(block.lower().translate(_FOLD) if not block.isascii() else block.lower())
        if _HAS_LEET.search(block):
            words = [w.translate(_LEET) if _HAS_LEET.search(w) and _HAS_LETTER.search(w) else w for w in words]
        if words:
            yield f" {' '.join(words)} "
        at = end


class Lexicon:
    """Weighted word beginnings, exception phrases and the curve from sums to a score."""

    def __init__(self, weights: dict[str, float], exceptions: set[str], curve: np.ndarray):
        self.weights, self.exceptions, self.curve = weights, exceptions, curve
        self.automaton = None

    def __getstate__(self):
        return self.weights, self.exceptions, self.curve

    def __setstate__(self, state):
        self.__init__(*state)

    def hits(self, text: str | None) -> tuple[float, int, int]:
        """Sum of weights (the longest entry of a word counts), hits, and words of a whole text."""
        if self.automaton is None:
            self.automaton = ahocorasick.Automaton()
            for w, x in self.weights.items():
                self.automaton.add_word(f" {w}", (x, len(w) + 1))
            self.automaton.make_automaton()
        total, n, words = 0.0, 0, 0
        for t in fold(text):
            words += t.count(" ") - 1
            if not self.weights:
                continue
            best: dict[int, tuple[int, float]] = {}
            for end, (x, length) in self.automaton.iter(t):
                start = end - length + 1
                if start not in best or best[start][0] < length:
                    best[start] = (length, x)
            for start, (_, x) in best.items():
                if self.exceptions and self._excepted(t, start):
                    continue
                total += x
                n += 1
        return total, n, words

    def _excepted(self, t: str, start: int) -> bool:
        after = t.index(" ", start + 1)
        word = t[start + 1 : after]
        before = t[t.rfind(" ", 0, start) + 1 : start] if start else ""
        following = t[after + 1 : t.find(" ", after + 1)] if after + 1 < len(t) else ""
        return f"{before} {word}" in self.exceptions or f"{word} {following}" in self.exceptions

    def score(self, text: str | None) -> float:
        total, n, words = self.hits(text)
        z = float(_features(total, n, words) @ self.curve)
        return float(1 / (1 + np.exp(-np.clip(z, -30, 30))))


def _features(total: float, n: int, words: int) -> np.ndarray:
    return np.array([1.0, np.log1p(total), total / (1 + np.log1p(words)), float(n > 0)])


def _terms(text: str | None) -> set[str]:
    """Distinct beginnings of a document's words."""
    words = {w for t in fold(text) for w in t.split()}
    return {w[:k] for w in words for k in range(LETTERS[0], min(LETTERS[1], len(w)) + 1)}


def _curve(x: np.ndarray, y: np.ndarray, rounds: int = 40) -> np.ndarray:
    """Logistic regression by Newton steps with a small ridge."""
    b = np.zeros(x.shape[1])
    for _ in range(rounds):
        p = 1 / (1 + np.exp(-np.clip(x @ b, -30, 30)))
        w = np.maximum(p * (1 - p), 1e-6)
        step = np.linalg.solve((x * w[:, None]).T @ x + 0.05 * np.eye(len(b)), x.T @ (y - p) - 0.05 * b)
        b = b + np.clip(step, -2, 2)
        if np.abs(step).max() < 1e-6:
            break
    return b


def fit(spark: SparkSession, docs: DataFrame, labels: DataFrame, training: Column, id_col: str = "doc_id", text_col: str = "text", label_col: str = "toxic", sample: int = SAMPLE, seed: int = 5) -> Lexicon:
    """Fit on labelled documents where ``training`` (over the id column) holds."""
    small_batches(spark)
    known = labels.where(F.col(label_col).isNotNull()).where(training).groupBy(id_col).agg(F.max(label_col).cast("int").alias("y"))
    n, positive = known.agg(F.count("*"), F.sum("y")).first()
    default = Lexicon({w: SEED_WEIGHT for w in SEED_WORDS}, set(), np.array([-4.0, 1.0, 1.0, 2.0]))
    if not n or not positive or positive == n:
        return default
    # Toxic documents are the rarer class: each class gets up to half of the sample, and weights below undo the difference.
    share = {0: min(1.0, sample / 2 / (n - positive)), 1: min(1.0, sample / 2 / positive)}
    u = F.pmod(F.xxhash64(F.lit(seed), id_col), F.lit(1 << 30)) / F.lit(float(1 << 30))
    drawn = known.where(u < F.when(F.col("y") == 1, share[1]).otherwise(share[0]))
    # The sample's ids and labels are bounded by its size, so they go to the texts and not the texts to them.
    rows = written(spark, docs.select(id_col, F.col(text_col).cast("string").alias("t")).join(F.broadcast(drawn), id_col).select("t", "y"), "labelled")

    def counted(batches):
        seen = {0: Counter(), 1: Counter()}
        for b in batches:
            for t, y in zip(b.column(0).to_pylist(), b.column(1).to_pylist()):
                seen[y].update(_terms(t))
        for y in (0, 1):
            yield from _packed(seen[y], y)

    def _packed(seen, y):
        keys = list(seen)
        for i in range(0, len(keys), 50_000):
            part = keys[i : i + 50_000]
            n = [seen[k] for k in part]
            zero = [0] * len(part)
            yield pa.RecordBatch.from_arrays([pa.array(part, pa.string()), pa.array(n if y else zero, pa.int64()), pa.array(zero if y else n, pa.int64())], names=["term", "tox", "rest"])

    n1, n0 = (rows.where(F.col("y") == y).count() for y in (1, 0))
    terms = rows.mapInArrow(counted, "term string, tox long, rest long").groupBy("term").agg(F.sum("tox").alias("tox"), F.sum("rest").alias("rest"))
    odds = F.log((F.col("tox") + 0.5) / F.lit(n1 + 1.0)) - F.log((F.col("rest") + 0.5) / F.lit(n0 + 1.0))
    best = terms.where(F.col("tox") >= SUPPORT).withColumn("odds", odds).where(F.col("odds") > ODDS).orderBy("term").collect()  # bounded with the sample
    weights = {r["term"]: float(r["odds"]) for r in best}
    for r in best:  # a longer entry that its own beginning already covers as well adds nothing
        t = r["term"]
        if any(t[:k] in weights and weights[t[:k]] >= weights[t] - 0.7 for k in range(LETTERS[0], len(t))):
            del weights[t]
    weights |= {w: max(SEED_WEIGHT, weights.get(w, 0)) for w in SEED_WORDS if not any(w[:k] in weights for k in range(LETTERS[0], len(w)))}
    def phrases(batches):
        seen = Counter()
        for b in batches:
            for text, y in zip(b.column(0).to_pylist(), b.column(1).to_pylist()):
                found = set()
                for t in fold(text):
                    words = t.split()
                    for i, w in enumerate(words):
                        if any(w[:k] in weights for k in range(LETTERS[0], min(LETTERS[1], len(w)) + 1)):
                            found |= {(f"{words[i - 1]} {w}", y)} if i else set()
                            found |= {(f"{w} {words[i + 1]}", y)} if i + 1 < len(words) else set()
                seen.update(found)
        keys = list(seen)
        yield pa.RecordBatch.from_arrays([pa.array([k for k, _ in keys], pa.string()), pa.array([y for _, y in keys], pa.int32()), pa.array([seen[k] for k in keys], pa.int64())], names=["phrase", "y", "n"])

    pairs = rows.mapInArrow(phrases, "phrase string, y int, n long").groupBy("phrase").agg(F.sum(F.when(F.col("y") == 1, F.col("n")).otherwise(0)).alias("tox"), F.sum(F.when(F.col("y") == 0, F.col("n")).otherwise(0)).alias("rest"))
    calm = pairs.where((F.col("rest") >= 3) & (F.col("rest") * F.lit(n1) > 4 * F.col("tox") * F.lit(n0)))
    lexicon = Lexicon(weights, {r["phrase"] for r in calm.collect()}, default.curve)

    def summed(batches):
        for b in batches:
            got = [lexicon.hits(t) for t in b.column(0).to_pylist()]
            yield pa.RecordBatch.from_arrays([b.column(1), pa.array([g[0] for g in got], pa.float64()), pa.array([g[1] for g in got], pa.int64()), pa.array([g[2] for g in got], pa.int64())], names=["y", "total", "n", "words"])

    got: pd.DataFrame = rows.select("t", "y").mapInArrow(summed, "y int, total double, n long, words long").toPandas()
    got = got.sort_values(["y", "total", "n", "words"])  # the order of partitions must not move the last digits
    x = np.stack([_features(a, b, c) for a, b, c in zip(got["total"], got["n"], got["words"])])
    lexicon.curve = _curve(x, got["y"].to_numpy(float))
    # The sample's share of toxic documents differs from that of all.
    lexicon.curve[0] += np.log(share[0] / share[1])
    return lexicon


def score(docs: DataFrame, lexicon: Lexicon, text_col: str = "text", keep: tuple[str, ...] = ("doc_id",)) -> DataFrame:
    """Columns ``keep`` with score (0 to 1) and hits."""
    small_batches(docs.sparkSession)

    def run(batches):
        for b in batches:
            texts = b.column(b.num_columns - 1).to_pylist()
            yield pa.RecordBatch.from_arrays([*b.columns[:-1], pa.array([lexicon.score(t) for t in texts], pa.float64())], names=[*keep, "score"])

    kinds = ", ".join(f"`{c}` {docs.schema[c].dataType.simpleString()}" for c in keep)
    return docs.select(*keep, F.col(text_col).cast("string").alias("_text")).mapInArrow(run, f"{kinds}, score double")
