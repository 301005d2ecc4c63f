"""Compression classifier: zstandard dictionaries of good and bad text, and the calibrated difference of compressed sizes."""

from __future__ import annotations

import math

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from .common import excerpt, held, light_batches, lowest, stage, table

#: Bounds of what is learned from: texts of each class for dictionaries, texts of each class for calibration, characters that are taken from all over a longer text.
DICT_TEXTS, FIT_TEXTS, MAX_CHARS, DICT_BYTES = 1200, 1200, 20_000, 112_640
#: Texts are compressed in pieces of so many bytes: in longer ones a text's own repetitions outweigh the dictionary.
PIECE = 256


def _pieces(data: bytes) -> list[bytes]:
    return [data[i : i + PIECE] for i in range(0, len(data), PIECE)] or [b""]


def labelled_sample(docs: DataFrame, labels: DataFrame, per_class: int) -> list:
    """At most per_class labelled texts of each quality, in the order of a hash of the id; of texts over MAX_CHARS, that many characters from all over them.

    Ids alone are joined with labels and chosen from; then the texts of the chosen, at most twice per_class ids, are read.
    """
    known = labels.where("quality in (0, 1)").groupBy(F.col("doc_id").alias("_id")).agg(F.max("quality").alias("quality"))
    usable = docs.where(F.length("text") > 0)
    ids = stage(usable.select("doc_id").distinct().join(known, F.col("doc_id") == F.col("_id")).select(F.xxhash64(F.lit(11), "doc_id").alias("h"), "doc_id", "quality"), "labelled")
    chosen = stage(lowest(ids.where("quality = 0"), per_class).union(lowest(ids.where("quality = 1"), per_class)).withColumnRenamed("doc_id", "_id"), "chosen")
    texts = stage(usable.join(F.broadcast(chosen), F.col("doc_id") == F.col("_id")).select("h", "doc_id", excerpt("text", MAX_CHARS).alias("text"), "quality"), "labelledtexts")
    return [r for q in (0, 1) for r in lowest(texts.where(F.col("quality") == q), per_class).collect()]


class Model:
    """score(text): 1 / (1 + exp(-(a * x + b))), x the difference of compressed sizes with the bad and the good dictionary over the plain size."""

    def __init__(self, good: bytes, bad: bytes, a: float = 0.0, b: float = 0.0, level: int = 3):
        self.good, self.bad, self.a, self.b, self.level, self._z = good, bad, a, b, level, None

    def __getstate__(self):
        return self.__dict__ | {"_z": None}

    def gain(self, text: str | None) -> float:
        import zstandard

        if self._z is None:
            self._z = [zstandard.ZstdCompressor(level=self.level, dict_data=zstandard.ZstdCompressionDict(d), write_content_size=False, write_dict_id=False) for d in (self.good, self.bad)]
        data = (text or "").encode("utf-8", "surrogatepass")
        pieces = _pieces(data)
        good, bad = (sum(len(z.compress(p)) for p in pieces) for z in self._z)
        return (bad - good) / max(good, bad)

    def score(self, text: str | None) -> float:
        return 1 / (1 + math.exp(-max(-60.0, min(60.0, self.a * self.gain(text) + self.b))))


def _dictionary(texts: list[str], size: int) -> bytes:
    """A trained dictionary, with its entropy tables, where training is possible; else, for few texts, the texts themselves."""
    import zstandard

    data = [p for t in texts for p in _pieces(t.encode("utf-8", "surrogatepass"))]
    try:
        return zstandard.train_dictionary(size, data).as_bytes()
    except zstandard.ZstdError:  # too few pieces
        return b"".join(data)[-size:]


def train(docs: DataFrame, labels: DataFrame, dict_texts: int = DICT_TEXTS, fit_texts: int = FIT_TEXTS) -> Model:
    """Learns from a bounded sample of labelled rows (see the constants): dictionaries from one part, the calibration by logistic regression, weighted to the sample's class sizes in labels, from the other."""
    rows = labelled_sample(docs, labels, dict_texts + fit_texts)
    by = {q: [r.text for r in rows if r.quality == q] for q in (0, 1)}
    if not by[0] or not by[1]:
        return Model(b"", b"", 0.0, 2.0 if by[1] else -2.0 if by[0] else 0.0)
    cut = {q: min(dict_texts, len(by[q]) // 2 or 1) for q in by}
    size = min(DICT_BYTES, *(sum(len(t) for t in by[q][: cut[q]]) for q in by))
    model = Model(*(_dictionary(by[q][: cut[q]], size) for q in (1, 0)))
    fit = {q: by[q][cut[q] :] or by[q] for q in by}
    counts = {r.quality: r.n for r in labels.where("quality in (0, 1)").groupBy("quality").agg(F.count(F.lit(1)).alias("n")).collect()}
    x = np.array([model.gain(t) for q in (0, 1) for t in fit[q]])
    y = np.repeat([0.0, 1.0], [len(fit[0]), len(fit[1])])
    w = np.where(y == 1, counts[1] / len(fit[1]), counts[0] / len(fit[0]))
    w /= w.sum()
    z, mean, sd = (x - x.mean()) / (x.std() or 1), x.mean(), x.std() or 1
    t, m = np.zeros(2), np.stack([z, np.ones_like(z)], 1)
    for _ in range(50):
        p = 1 / (1 + np.exp(-np.clip(m @ t, -60, 60)))
        step = np.linalg.solve((m * (w * p * (1 - p))[:, None]).T @ m + 1e-4 * np.eye(2), m.T @ (w * (p - y)) + 1e-4 * t)
        t -= step
        if abs(step).max() < 1e-9:
            break
    model.a, model.b = float(t[0] / sd), float(t[1] - t[0] * mean / sd)
    return model


def classify(docs: DataFrame, model: Model, threshold: float = 0.3) -> DataFrame:
    """docs with score double and predicted int, from the whole text alone. Null text is empty; an empty text has the score of an even compression.

    Rows that repeat get equal scores; other columns pass through, and columns named like the added ones are replaced.
    """
    @F.arrow_udf("double")
    def score(texts: pa.Array) -> pa.Array:
        return pa.array([model.score(t.as_py()) for t in texts], pa.float64())

    light_batches(docs.sparkSession)  # only texts go to Python, and numbers come back
    return docs.withColumn("score", score("text")).withColumn("predicted", (F.col("score") >= threshold).cast("int"))


def op6_quality_classifier(spark: SparkSession, sf_dir: str) -> DataFrame:
    docs, labels = (table(spark, sf_dir, t) for t in ("documents", "labels"))
    docs = docs.select("doc_id", "text")
    model = train(docs.where(held("doc_id", 5) != 0), labels.where(held("doc_id", 5) != 0))
    return classify(docs, model).select("doc_id", (held("doc_id", 5) == 0).alias("held_out"), "score", "predicted")
