"""Language identification: sparse multinomial logistic regression on TF-IDF of character n-grams, with temperature calibration."""

from __future__ import annotations

import re

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import Window as W
from pyspark.sql import functions as F
from pyspark.sql import types as T

from .common import excerpt, held, light_batches, stage, table

#: Hash bits, n-gram lengths; bounds of the training sample: rows in all (at least 20 a language), characters that are taken from all over a longer text.
BITS, GRAMS, MAX_ROWS, MAX_CHARS = 14, (1, 2, 3), 6000, 4000
WORDLIKE = re.compile(r"[^\W\d_]")


def has_letter(text: str) -> bool:
    """The pattern also finds numerals such as a half or a superscript two, which are no letters."""
    return any(m.group().isalpha() for m in WORDLIKE.finditer(text))


def counts(text: str) -> np.ndarray:
    """Counts of hashed n-grams of the lower-cased text with a space at either end; white space counts as a space."""
    c = np.frombuffer((" " + re.sub(r"\s+", " ", text.lower()) + " ").encode("utf-32-le", "surrogatepass"), np.uint32)
    total = np.zeros(1 << BITS, np.float64)
    h = np.zeros(len(c), np.uint32)
    for n in range(1, max(GRAMS) + 1):
        h = h[: len(c) - n + 1] * np.uint32(0x01000193) + c[n - 1 :] + np.uint32(n)
        if n in GRAMS and len(h):
            total += np.bincount((h * np.uint32(0x9E3779B1)) >> np.uint32(32 - BITS), minlength=1 << BITS)
    return total


class Model:
    def __init__(self, langs: list[str], idf: np.ndarray, weights: np.ndarray, bias: np.ndarray, temperature: float = 1.0):
        self.langs, self.idf, self.weights, self.bias, self.temperature = langs, idf, weights, bias, temperature

    def features(self, text: str) -> tuple[np.ndarray, np.ndarray]:
        t = counts(text)
        i = np.flatnonzero(t)
        v = (1 + np.log(t[i])) * self.idf[i]
        return i, v / (np.sqrt((v * v).sum()) or 1)

    def logits(self, text: str) -> np.ndarray:
        i, v = self.features(text)
        return v @ self.weights[i] + self.bias

    def predict(self, text: str | None) -> tuple[str, float]:
        if not text or not self.langs or not has_letter(text):
            return "und", 0.0
        z = self.logits(text) / self.temperature
        p = np.exp(z - z.max())
        k = int(p.argmax())
        return self.langs[k], float(p[k] / p.sum())


def train(docs: DataFrame, rows: int = MAX_ROWS, alpha: float = 0.5, beta: float = 1.0, l1: float = 0.02, l2: float = 0.02, epochs: int = 2) -> Model:
    """Learns from at most max(rows, 20 a language) rows with text and lang, the first of each language by a hash of the id, in equal shares; of longer texts MAX_CHARS characters from all over them.

    Every language with a letter in a chosen text is learned. Follow-the-regularised-leader: per coordinate sums z and squared gradients n; weights are zero while |z| <= l1, and shrunk by l2 and the
    coordinate's own rate otherwise. A fifth of the rows is kept to set the temperature that gives the least log loss.
    """
    usable = docs.where(F.col("lang").isNotNull() & (F.length("text") > 0))
    ids = stage(usable.select(F.xxhash64(F.lit(13), "doc_id").alias("h"), "doc_id", "lang"), "langids")
    each = max(20, rows // max(1, ids.select("lang").distinct().count()))
    first = W.partitionBy("lang").orderBy("h", "doc_id")  # a limit on its rank is applied in each task before the shuffle
    chosen = stage(ids.withColumn("rank", F.row_number().over(first)).where(F.col("rank") <= each).select(F.col("doc_id").alias("_id"), F.col("lang").alias("_lang")).distinct(), "langchosen")
    same = F.col("doc_id").eqNullSafe(F.col("_id")) & (F.col("lang") == F.col("_lang"))
    texts = stage(usable.join(F.broadcast(chosen), same).select(F.xxhash64(F.lit(13), "doc_id").alias("h"), excerpt("text", MAX_CHARS).alias("text"), "lang"), "langtexts")
    by = W.partitionBy("lang").orderBy("h", "text")  # ids may repeat
    seen = texts.withColumn("rank", F.row_number().over(by)).where(F.col("rank") <= each).select("h", "text", "lang").collect()
    seen = sorted((r for r in seen if has_letter(r.text)), key=lambda r: (r.h, r.text))
    langs = sorted({r.lang for r in seen})
    if not seen:
        return Model([], np.ones(1 << BITS), np.zeros((1 << BITS, 0)), np.zeros(0))
    k, y = len(langs), [langs.index(r.lang) for r in seen]
    raw, df = [], np.zeros(1 << BITS)
    for r in seen:
        t = counts(r.text)
        at = np.flatnonzero(t)
        df[at] += 1
        raw.append((at.astype(np.int32), t[at].astype(np.float32)))
    model = Model(langs, np.log((1 + len(raw)) / (1 + df)) + 1, np.zeros((1 << BITS, k)), np.zeros(k))
    fit = [i for i in range(len(seen)) if i % 5 or len(seen) < 5]
    feats = {}
    for i, (at, t) in enumerate(raw):
        v = (1 + np.log(t)) * model.idf[at]
        feats[i] = (at, (v / np.sqrt((v * v).sum())).astype(np.float32))
    z, n = np.zeros((1 << BITS, k)), np.zeros((1 << BITS, k))
    zb, nb = np.zeros(k), np.zeros(k)
    weight = lambda z, n: np.where(np.abs(z) <= l1, 0.0, -(z - np.sign(z) * l1) / ((beta + np.sqrt(n)) / alpha + l2))
    for _ in range(epochs):
        for i in fit:
            at, v = feats[i]
            w, b = weight(z[at], n[at]), weight(zb, nb)
            s = v @ w + b
            p = np.exp(s - s.max())
            p /= p.sum()
            p[y[i]] -= 1
            for zz, nn, g, ww, where in ((z, n, v[:, None] * p, w, at), (zb, nb, p, b, slice(None))):
                new = nn[where] + g * g
                zz[where] += g - (np.sqrt(new) - np.sqrt(nn[where])) / alpha * ww
                nn[where] = new
    model.weights, model.bias = weight(z, n), weight(zb, nb)
    kept = [i for i in range(len(seen)) if i % 5 == 0]
    s = np.array([feats[i][1] @ model.weights[feats[i][0]] + model.bias for i in kept])
    s -= s.max(1, keepdims=True)
    own = [y[i] for i in kept]

    def loss(t):
        q = s / t
        return float((np.log(np.exp(q).sum(1)) - q[range(len(q)), own]).mean())

    model.temperature = float(min(np.geomspace(0.05, 5, 60), key=loss))
    return model


def identify(docs: DataFrame, model: Model) -> DataFrame:
    """docs with lang_pred and score: `und` and 0 for null, empty and letterless texts; else a learned language and its calibrated probability.

    The whole text counts. Columns named like the added ones are replaced; other columns pass through.
    """
    light_batches(docs.sparkSession)
    docs = docs.drop("lang_pred", "score")
    schema = T.StructType([*docs.schema.fields]).add("lang_pred", "string").add("score", "double")
    names = docs.columns
    at = names.index("text")

    def run(batches):
        for b in batches:
            got = [model.predict(t.as_py()) for t in b.column(at)]
            yield pa.RecordBatch.from_arrays([*b.columns, pa.array([x for x, _ in got], pa.string()), pa.array([x for _, x in got], pa.float64())], names=[*names, "lang_pred", "score"])

    return docs.mapInArrow(run, schema)


def op7_language_id(spark: SparkSession, sf_dir: str) -> DataFrame:
    docs = table(spark, sf_dir, "documents").select("doc_id", "text", "lang")
    model = train(docs.where(held("doc_id", 4) != 2))
    return identify(docs.select("doc_id", "text"), model).select("doc_id", (held("doc_id", 4) == 2).alias("held_out"), "lang_pred", "score")
