"""Language identification: sparse multinomial logistic regression on TF-IDF character n-grams.

Document frequencies and languages are counted over all training documents.  Weights are fitted on a
bounded, documented sample, dealt out by language, by follow-the-regularised-leader steps with
elastic-net penalties, and one temperature is fitted on a part of the sample that the weights have not seen.
"""

from __future__ import annotations

from collections import Counter
from collections.abc import Iterator

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from flowrings.llm.arrow import byte_rows, documents_view, held_out

BITS = 16


def ngram_counts(text: str) -> tuple[np.ndarray, np.ndarray]:
    """Hashed character 1- to 3-grams of the lower-cased text that hold a letter, and their counts.

    All but letters count as a space and runs of spaces as one, so digits and marks say nothing.
    """
    low = "".join([c if c.isalpha() else " " for c in text.lower()]) if not text.isascii() else text.lower().translate(_SPACED)
    low = " " + " ".join(low.split()) + " "
    if low == "  ":
        return np.empty(0, np.int64), np.empty(0)
    a = np.frombuffer(low.encode("utf-32-le"), np.uint32).astype(np.uint64)
    h, out = np.zeros(len(a), np.uint64), []
    for n in (1, 2, 3):
        h = h[: len(a) - n + 1] * np.uint64(0x100000001B3) + a[n - 1 :] + np.uint64(n)
        out.append(h * np.uint64(0x9E3779B97F4A7C15) >> np.uint64(64 - BITS))
    counts = np.bincount(np.concatenate(out).astype(np.int64), minlength=1 << BITS)
    at = np.flatnonzero(counts)
    return at, counts[at].astype(float)


_SPACED = {i: " " for i in range(128) if not chr(i).isalpha()}


class LanguageModel:
    """IDF and weights by hash value, class names, temperature."""

    def __init__(self, idf: np.ndarray, weights: np.ndarray, bias: np.ndarray, classes: list[str], temperature: float = 1.0):
        self.idf, self.weights, self.bias, self.classes, self.temperature = idf, weights, bias, classes, temperature

    def vector(self, at: np.ndarray, counts: np.ndarray) -> np.ndarray:
        x = (1 + np.log(counts)) * self.idf[at]
        return x / max(1e-12, np.sqrt((x * x).sum()))

    def logits(self, at: np.ndarray, counts: np.ndarray) -> np.ndarray:
        return self.vector(at, counts) @ self.weights[at] + self.bias

    def predict(self, text: str) -> tuple[str, float]:
        at, counts = ngram_counts(text)
        if not len(at) or not self.classes:
            return "und", 0.0
        z = self.logits(at, counts) / self.temperature
        p = np.exp(z - z.max())
        return self.classes[int(z.argmax())], float(p.max() / p.sum())


def ftrl(rows: list[tuple[np.ndarray, np.ndarray, int]], n_classes: int, *, epochs: int = 3, alpha: float = 0.5, beta: float = 1.0, l1: float = 0.05, l2: float = 0.01) -> tuple[np.ndarray, np.ndarray]:
    """Weights and bias after ``epochs`` passes over (features, values, class), one step a row.

    Each coordinate keeps the sum of its adjusted gradients and of their squares; its weight is the
    minimiser of the regularised linearised loss, exactly zero while the sum is within ``l1``.
    """
    size = 1 << BITS
    z, n = np.zeros((size + 1, n_classes)), np.zeros((size + 1, n_classes))

    def weight(at: np.ndarray) -> np.ndarray:
        zz = z[at]
        shrunk = np.sign(zz) * np.maximum(np.abs(zz) - np.where(at[:, None] == size, 0.0, l1), 0.0)
        return -shrunk / ((beta + np.sqrt(n[at])) / alpha + l2)

    for _ in range(epochs):
        for at, x, y in rows:
            at, x = np.append(at, size), np.append(x, 1.0)
            w = weight(at)
            s = x @ w
            p = np.exp(s - s.max())
            p /= p.sum()
            p[y] -= 1
            g = np.outer(x, p)
            root = np.sqrt(n[at])
            n[at] += g * g
            z[at] += g - (np.sqrt(n[at]) - root) / alpha * w
    w = weight(np.arange(size + 1))
    return w[:size], w[size]


def fit_temperature(logits: np.ndarray, y: np.ndarray) -> float:
    """The temperature of least log loss, by golden-section search on its logarithm."""
    if not len(y):
        return 1.0

    def loss(t: float) -> float:
        z = logits / np.exp(t)
        z = z - z.max(axis=1, keepdims=True)
        return float((np.log(np.exp(z).sum(axis=1)) - z[np.arange(len(y)), y]).mean())

    lo, hi, ratio = np.log(0.05), np.log(20.0), (5**0.5 - 1) / 2
    for _ in range(40):
        a, b = hi - ratio * (hi - lo), lo + ratio * (hi - lo)
        lo, hi = (lo, b) if loss(a) <= loss(b) else (a, hi)
    return float(np.exp((lo + hi) / 2))


def quotas(counts: dict[str, int], sample: int, least: int) -> dict[str, int]:
    """Documents to take of each language: its share of ``sample``, ``least`` where that is less, never more than it has."""
    total = max(1, sum(counts.values()))
    return {k: min(n, max(least, round(sample * n / total))) for k, n in counts.items()}


def train(
    docs: DataFrame, sample: int = 4_000, calibrate: float = 0.2, least: int = 40, id_col: str = "doc_id", text_col: str = "text", lang_col: str = "lang"
) -> LanguageModel:
    """Learn from documents with a language that are not held out; weights from about ``sample`` of them.

    Every language of the training documents is a class.  The sample takes each language's share of
    ``sample``, at least ``least`` documents (all of a language that has fewer), the first by a hash of the
    id; of each language the part ``calibrate`` is set aside for the temperature.  Null texts, null
    languages and null ids are left out; repeated rows enter the sample once.  Without any training document
    every prediction is ``und``.
    """
    known = docs.select(F.col(f"`{id_col}`").alias("doc_id"), F.col(f"`{text_col}`").alias("text"), F.col(f"`{lang_col}`").alias("lang"))
    known = known.filter(F.col("lang").isNotNull() & F.col("text").isNotNull() & F.col("doc_id").isNotNull() & ~held_out())

    def frequencies(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        df, of = np.zeros(1 << BITS, np.int64), Counter()
        for batch in batches:
            for raw, lang in byte_rows(batch, ["text", "lang"]):
                at = ngram_counts(raw.decode())[0]
                df[at] += 1
                of[lang.decode()] += len(at) > 0
        at = np.flatnonzero(df)
        yield pa.RecordBatch.from_arrays([pa.array([*at.tolist(), *[-1] * len(of)], pa.int64()), pa.array([*[None] * len(at), *of], pa.string()), pa.array([*df[at].tolist(), *of.values()], pa.int64())], ["feature", "lang", "n"])

    counted = known.select("text", "lang").mapInArrow(frequencies, "feature long, lang string, n long").groupBy("feature", "lang").agg(F.sum("n").alias("n")).toArrow()
    feature, n = counted.column("feature").to_numpy(), counted.column("n").to_numpy()
    of = {k: int(x) for k, x in zip(counted.column("lang").to_pylist(), n.tolist()) if k is not None and x > 0}
    df = np.zeros(1 << BITS)
    df[feature[feature >= 0]] = n[feature >= 0]
    idf = np.log((1 + sum(of.values())) / (1 + df)) + 1
    classes = sorted(of)
    model = LanguageModel(idf, np.zeros((1 << BITS, len(classes))), np.zeros(len(classes)), classes)
    if not classes:
        return model

    def vectors(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in batches:
            out = []
            for doc_id, order, raw, lang in byte_rows(batch, ["doc_id", "order", "text", "lang"]):
                at, counts = ngram_counts(raw.decode())
                if len(at):
                    out.append((doc_id, order, lang.decode(), at.astype(np.int32).tobytes(), counts.astype(np.int32).tobytes()))
            cols = list(zip(*out)) or [()] * 5
            yield pa.RecordBatch.from_arrays([pa.array(c, t) for c, t in zip(cols, (pa.int64(), pa.int64(), pa.string(), pa.binary(), pa.binary()))], ["doc_id", "order", "lang", "at", "counts"])

    # a hash limit by language that lets a little more than its quota through: one scan, no sort of the corpus
    wanted = quotas(of, sample, least)
    limit = {k: min(1.0, (q + 6 * q**0.5 + 20) / of[k]) for k, q in wanted.items()}
    limits = docs.sparkSession.createDataFrame([(k, min(int(x * (1 << 63)), (1 << 63) - 1)) for k, x in limit.items()], "lang string, below long")
    drawn = known.withColumn("order", F.shiftrightunsigned(F.xxhash64("doc_id", "text", "lang"), 1)).join(F.broadcast(limits), "lang").filter("order <= below")
    got = drawn.dropDuplicates(["order"]).select("doc_id", "order", "text", "lang").mapInArrow(vectors, "doc_id long, order long, lang string, at binary, counts binary").toArrow()
    rows, rest, taken = [], [], Counter()
    for r in got.sort_by([(c, "ascending") for c in ("order", "doc_id", "lang", "at", "counts")]).to_pylist():
        k = r["lang"]
        if taken[k] < wanted[k]:
            at = np.frombuffer(r["at"], np.int32).astype(np.int64)
            held = int((taken[k] + 1) * calibrate) > int(taken[k] * calibrate)  # every fifth of a language at 0.2
            (rest if held else rows).append((at, model.vector(at, np.frombuffer(r["counts"], np.int32)), classes.index(k)))
            taken[k] += 1
    model.weights, model.bias = ftrl(rows, len(classes)) if rows else (model.weights, model.bias)
    logits = np.array([x @ model.weights[at] + model.bias for at, x, _ in rest])
    model.temperature = fit_temperature(logits, np.array([y for _, _, y in rest], np.int64))
    return model


def predict(docs: DataFrame, model: LanguageModel, id_col: str = "doc_id", text_col: str = "text") -> DataFrame:
    """One row per input row: doc_id, lang_pred, score.  ``und`` with score 0 for null texts and texts without letters.

    Equal scores go to the first class by name.  Rows are judged by their own text, whatever their ids.
    """
    known = docs.sparkSession.sparkContext.broadcast(model)

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in batches:
            out = [(doc_id, *known.value.predict((raw or b"").decode())) for doc_id, raw in byte_rows(batch, ["doc_id", "text"])]
            cols = list(zip(*out)) or [()] * 3
            yield pa.RecordBatch.from_arrays([pa.array(c, t) for c, t in zip(cols, (pa.int64(), pa.string(), pa.float64()))], ["doc_id", "lang_pred", "score"])

    return documents_view(docs, id_col, text_col).mapInArrow(run, "doc_id long, lang_pred string, score double")


def op7_langid(spark: SparkSession, sf_dir: str) -> DataFrame:
    docs = spark.read.parquet(f"{sf_dir}/documents.parquet")
    return predict(docs, train(docs)).select("doc_id", held_out().alias("held_out"), "lang_pred", "score")
