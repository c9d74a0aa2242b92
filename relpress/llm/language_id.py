"""Language identification by nearest centroid over normalised TF-IDF vectors of character n-grams.

Method. A text's letters (lower case, one blank between words) give counts of 1- to 3-grams of UTF-8 bytes, hashed into
``DIM`` buckets; counts are damped by a logarithm, weighted by inverse document frequency and normalised. Each language
has several centroids, from spherical k-means. A text gets the language of the most similar centroid (cosine). It is
rejected if its similarity is well under the least seen among training texts of that language and of its length.

Fitting. Document frequencies count every training document. Centroids are fitted on a sample bounded by
``PER_LANGUAGE`` expected documents a language, drawn by a hash of the id; each language is fitted in one task.

Edge cases. A null text, or one without a letter, is ``und`` with score 0 and counts as rejected. Rows without a language
do not train. Without any training row every text is ``und``. Equally near centroids: the language that sorts first. Very
long texts are counted in blocks that end between words, with the counts of the whole. An empty table gives an empty table.
Repeated rows give repeated results and count repeatedly. Only the id, text and language columns are read.
"""

from __future__ import annotations

import numpy as np
import pandas as pd
import pyarrow as pa
import regex
from pyspark.sql import Column, DataFrame, SparkSession
from pyspark.sql import functions as F

from .common import small_batches, written

DIM, CENTROIDS, PER_LANGUAGE, ROUNDS = 8192, 4, 1000, 12
#: Rejected under this part of the least similarity of training texts of like length; bands of length in doublings.
REJECT, BANDS = 0.35, 8
_NOT_LETTER = regex.compile(r"[^\p{L}\p{M}]+")
_LETTER = regex.compile(r"\p{L}")
_BLOCK = 1 << 20


def _blocks(text: str):
    """The text in blocks that end before a character that is no letter, so that no word is cut."""
    at = 0
    while at < len(text):
        gap = _NOT_LETTER.search(text, min(len(text), at + _BLOCK))
        end = gap.start() if gap else len(text)
        yield text[at : max(end, at + 1)]
        at = max(end, at + 1)


def _counted(before: bytes, more: bytes) -> np.ndarray:
    """Hashed counts of the grams that end in ``more``, with the two bytes before it."""
    a = np.frombuffer(before + more, np.uint8).astype(np.uint32)
    k = len(before)
    two = a[:-1] << 8 | a[1:]
    three = two[:-1] << 8 | a[2:]
    # 1-grams keep a place of their own; longer ones are spread over the rest by a multiplicative hash.
    spread = np.concatenate([two[max(0, k - 1) :] * np.uint32(2654435761), (three[max(0, k - 2) :] + np.uint32(0x5000000)) * np.uint32(2246822519)]) >> np.uint32(8)
    return np.bincount(np.concatenate([a[k:], 256 + spread % np.uint32(DIM - 256)]), minlength=DIM)


def gram_counts(text: str | None) -> np.ndarray | None:
    """Hashed counts of byte 1- to 3-grams over the letters of a whole text; None if it has no letter."""
    if not text or not _LETTER.search(text):
        return None
    total, before = np.zeros(DIM, np.int64), b""
    for block in _blocks(text):
        letters = _NOT_LETTER.sub(" ", block.lower()).strip()
        if letters:
            more = f" {letters}".encode("utf-8", "surrogatepass")
            total += _counted(before, more)
            before = (before + more)[-2:]
    return total + _counted(before, b" ")


def _vector(counts: np.ndarray, idf: np.ndarray) -> np.ndarray:
    v = np.log1p(counts.astype(np.float32)) * idf
    return v / max(float(np.sqrt(v @ v)), 1e-12)


def _band(counts: np.ndarray) -> int:
    """Doublings of the number of letters' bytes, from 16 on."""
    return int(min(BANDS - 1, max(0, np.log2(max(1, counts[:256].sum() / 16)))))


def _frequencies(batches):
    """One row per bucket and task: documents of the task that have it; and the number of documents as bucket -1."""
    seen, n = np.zeros(DIM, np.int64), 0
    for b in batches:
        for t in b.column(0).to_pylist():
            if (c := gram_counts(t)) is not None:
                seen += c > 0
                n += 1
    if n:
        yield pa.RecordBatch.from_arrays([pa.array(np.r_[-1, np.arange(DIM)], pa.int32()), pa.array(np.r_[n, seen], pa.int64())], names=["bucket", "n"])


def _cluster(x: np.ndarray, k: int, seed: int) -> np.ndarray:
    """Spherical k-means with far-apart starting points; centroids of unit length."""
    rng = np.random.default_rng(seed)
    at = [int(rng.integers(len(x)))]
    near = x @ x[at[0]]
    for _ in range(1, min(k, len(x))):
        at.append(int(np.argmin(near)))
        near = np.maximum(near, x @ x[at[-1]])
    c = x[at].copy()
    for _ in range(ROUNDS):
        own = np.argmax(x @ c.T, axis=1)
        for j in range(len(c)):
            if (m := x[own == j]).size:
                s = m.sum(axis=0)
                c[j] = s / max(float(np.sqrt(s @ s)), 1e-12)
    return c


class Model:
    """idf, centroids with their languages, and the least similarity by language and band of length."""

    def __init__(self, idf: np.ndarray, langs: list[str], centroids: np.ndarray, floor: dict[str, np.ndarray]):
        self.idf, self.langs, self.centroids, self.floor = idf, langs, centroids, floor

    def predict(self, text: str | None) -> tuple[str, float, bool]:
        c = gram_counts(text)
        if c is None or not self.langs:
            return "und", 0.0, True
        near = self.centroids @ _vector(c, self.idf)
        best = int(np.argmax(near))
        lang, score = self.langs[best], float(min(1.0, max(0.0, near[best])))
        return lang, score, score < REJECT * float(self.floor[lang][_band(c)])


def fit(spark: SparkSession, docs: DataFrame, training: Column, id_col: str = "doc_id", text_col: str = "text", lang_col: str = "lang", per_language: int = PER_LANGUAGE, seed: int = 11) -> Model:
    """Fit on the rows where ``training`` holds and the language is known."""
    small_batches(spark)
    rows = docs.where(training & F.col(lang_col).isNotNull()).select(F.col(id_col).alias("i"), F.col(text_col).cast("string").alias("t"), F.col(lang_col).cast("string").alias("l"))
    df = rows.select("t").mapInArrow(_frequencies, "bucket int, n long").groupBy("bucket").agg(F.sum("n").alias("n")).collect()
    if not df:
        return Model(np.ones(DIM, np.float32), [], np.zeros((0, DIM), np.float32), {})
    seen = {r["bucket"]: r["n"] for r in df}
    n = seen.pop(-1)
    idf = np.array([np.log((1 + n) / (1 + seen.get(i, 0))) + 0.1 for i in range(DIM)], np.float32)

    # Expected documents a language are bounded; which ones, the hash of the id says.
    held = {r["l"]: r["count"] for r in rows.groupBy("l").count().collect()}
    share = F.create_map(*[F.lit(x) for k, v in held.items() for x in (k, min(1.0, per_language / v))])
    u = F.pmod(F.xxhash64(F.lit(seed), "i"), F.lit(1 << 30)) / F.lit(float(1 << 30))
    sample = rows.where(u < share[F.col("l")]).select("l", "t", u.alias("u"))

    def centroids(key: tuple, group: pd.DataFrame) -> pd.DataFrame:
        group = group.sort_values(["u", "t"])  # the order of arrival must not move the centroids
        x, band = np.empty((len(group), DIM), np.float32), []
        for t in group["t"]:
            if (c := gram_counts(t)) is not None:
                x[len(band)] = _vector(c, idf)
                band.append(_band(c))
        if not band:
            return pd.DataFrame({"l": [], "kind": [], "values": []})
        x, band = x[: len(band)], np.array(band)
        c = _cluster(x, CENTROIDS, seed)
        near = (x @ c.T).max(axis=1)
        floor = np.array([near[band == b].min() if (band == b).any() else np.nan for b in range(BANDS)], np.float32)
        # A band without texts takes the nearest lower one's figure, as longer texts are more alike; the first, the least.
        floor[0] = np.nanmin(floor) if np.isnan(floor[0]) else floor[0]
        for b in range(1, BANDS):
            floor[b] = floor[b - 1] if np.isnan(floor[b]) else floor[b]
        return pd.DataFrame({"l": key[0], "kind": [*range(len(c)), -1], "values": [*map(bytes, c.astype("<f4")), floor.astype("<f4").tobytes()]})

    fitted = written(spark, sample.groupBy("l").applyInPandas(centroids, "l string, kind int, values binary"), "centroids")
    got = sorted(fitted.collect(), key=lambda r: (r["l"], r["kind"]))
    floor = {r["l"]: np.frombuffer(r["values"], "<f4") for r in got if r["kind"] == -1}
    own = [r for r in got if r["kind"] >= 0]
    return Model(idf, [r["l"] for r in own], np.stack([np.frombuffer(r["values"], "<f4") for r in own]) if own else np.zeros((0, DIM), np.float32), floor)


def identify(docs: DataFrame, model: Model, text_col: str = "text", keep: tuple[str, ...] = ("doc_id",)) -> DataFrame:
    """Columns ``keep`` with lang_pred, score and rejected."""
    small_batches(docs.sparkSession)

    def run(batches):
        for b in batches:
            got = [model.predict(t) for t in b.column(b.num_columns - 1).to_pylist()]
            yield pa.RecordBatch.from_arrays(
                [*b.columns[:-1], pa.array([g[0] for g in got], pa.string()), pa.array([g[1] for g in got], pa.float64()), pa.array([g[2] for g in got], pa.bool_())],
                names=[*keep, "lang_pred", "score", "rejected"],
            )

    kinds = ", ".join(f"`{c}` {docs.schema[c].dataType.simpleString()}" for c in keep)
    return docs.select(*keep, F.col(text_col).cast("string").alias("_text")).mapInArrow(run, f"{kinds}, lang_pred string, score double, rejected boolean")


def accepted(docs: DataFrame, model: Model, text_col: str = "text") -> DataFrame:
    """The rows of ``docs`` whose text is not rejected, all columns as they are."""
    small_batches(docs.sparkSession)

    def run(batches):
        for b in batches:
            yield b.filter(pa.array([not model.predict(t)[2] for t in b.column(text_col).to_pylist()], pa.bool_()))

    return docs.mapInArrow(run, docs.schema)
