"""Toxicity by multiple-instance learning: a document is toxic if one of its sentences is.

Sentence features are hashed character 4- to 6-grams that do not cross words.  A sentence's logit is a
bias plus the weights of its features; a document's score is the noisy-or of its sentences, and the
weights are learned from document labels through it.  The same sentence scores locate the offence.

Only features that lean towards toxic documents in the labelled sample take part; the sample is the
documented bound (``sample`` documents).  Scoring covers every document and its whole text.
"""

from __future__ import annotations

from collections.abc import Iterator

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from flowrings.llm.arrow import byte_rows, documents_view, held_out, keep_rows
from flowrings.llm.sample import sample_ids

BITS = 20
#: The bias of a model that has learned nothing: the noisy-or of any number of sentences stays near 0.
NO_EVIDENCE = -40.0
# Bytes that end a sentence become 10; other ASCII bytes that are no letter or digit become 32.
_TABLE = bytes(10 if c in b".!?\n" else c if 48 <= c <= 57 or 97 <= c <= 122 or c >= 128 else 32 for c in range(256))


def features(text: str) -> tuple[np.ndarray, np.ndarray, int]:
    """Feature numbers, the sentence of each, and the number of sentences."""
    raw = text.lower().encode().translate(_TABLE)
    a = np.frombuffer(b" " + raw + b" ", np.uint8)
    ends = a == 10
    sentence = np.cumsum(ends)
    spaces = np.cumsum(a <= 32)
    out, where, h = [], [], np.zeros(len(a), np.uint64)
    wide = a.astype(np.uint64) + np.uint64(1)
    for n in range(1, 7):
        m = len(a) - n + 1
        if m <= 0:
            break
        h = h[:m] * np.uint64(0x100000001B3) + wide[n - 1 :]
        if n >= 4:
            own = np.flatnonzero(spaces[n - 2 : n - 2 + m] == spaces[:m])
            out.append((h[own] * np.uint64(0x9E3779B97F4A7C15) >> np.uint64(64 - BITS)).astype(np.int32))
            where.append(sentence[own + 1])
    n_sentences = int(sentence[-1]) + 1 if raw.strip() else 0
    return (np.concatenate(out) if out else np.empty(0, np.int32)), (np.concatenate(where) if where else np.empty(0, np.int64)), n_sentences


class MilModel:
    """Weights of the selected features (dense over all hash values) and the bias of a sentence."""

    def __init__(self, weights: np.ndarray, bias: float):
        self.weights, self.bias = weights.astype(np.float32), float(bias)

    def sentence_scores(self, text: str) -> np.ndarray:
        f, where, n = features(text)
        z = np.bincount(where, self.weights[f], max(n, 1))[: max(n, 1)] + self.bias
        return 1 / (1 + np.exp(-np.clip(z, -40, 40))) if n else np.empty(0)

    def score(self, text: str) -> float:
        return noisy_or(self.sentence_scores(text))


def noisy_or(p: np.ndarray) -> float:
    return float(-np.expm1(np.log1p(-np.minimum(p, 1 - 1e-9)).sum())) if len(p) else 0.0


def _fit(bags: list[tuple[int, int, np.ndarray, np.ndarray]], n_features: int, l2: float = 0.02, steps: int = 400, rate: float = 0.05) -> tuple[np.ndarray, float]:
    """Gradient steps (Adam) on the noisy-or likelihood of (label, sentences, sentence numbers, features)."""
    label = np.array([b[0] for b in bags], float)
    plain = np.empty(len(bags))  # sentences without a selected feature: all share the bias as logit
    row_of, feat, bag_of, n_rows = [], [], [], 0
    for i, (_, n, where, f) in enumerate(bags):
        u, inverse = np.unique(where, return_inverse=True)
        plain[i] = n - len(u)
        row_of.append(inverse + n_rows)
        feat.append(f)
        bag_of.append(np.full(len(u), i))
        n_rows += len(u)
    row_of, feat, bag_of = (np.concatenate(x).astype(np.int64) if x else np.empty(0, np.int64) for x in (row_of, feat, bag_of))
    w, bias = np.zeros(n_features), -6.0
    m, v = np.zeros(n_features + 1), np.zeros(n_features + 1)
    size = max(1, len(bags))
    for t in range(1, steps + 1):
        z = np.bincount(row_of, w[feat], n_rows) + bias
        p, q = 1 / (1 + np.exp(-np.clip(z, -40, 40))), 1 / (1 + np.exp(-bias))
        soft = np.bincount(bag_of, np.logaddexp(0, z), len(bags)) + plain * np.logaddexp(0, bias)
        d = np.maximum(-np.expm1(-soft), 1e-9)
        slope = np.where(label > 0, -(1 - d) / d, 1.0)  # of the loss by each sentence's logit, over its probability
        g_row = slope[bag_of] * p
        g = np.append(np.bincount(feat, g_row[row_of], n_features) / size + l2 * w / size, (g_row.sum() + (slope * plain).sum() * q) / size)
        m, v = 0.9 * m + 0.1 * g, 0.999 * v + 0.001 * g * g
        step = rate * (m / (1 - 0.9**t)) / (np.sqrt(v / (1 - 0.999**t)) + 1e-8)
        w, bias = w - step[:-1], bias - step[-1]
    return w, bias


def train(docs: DataFrame, labels: DataFrame, sample: int = 10_000, most_features: int = 4_000, least_lift: float = 4.0) -> MilModel:
    """Fit on at most ``sample`` labelled documents that are not held out.

    A document labelled more than once counts with its largest label; null labels and ids are left
    out.  Features need a lift of ``least_lift`` standard errors or, where labels are too few for any
    to get there, 0.7 of the greatest lift.  Without both labels no sentence is evidence: the model then
    scores every text as good as 0, whatever its length.
    """
    chosen = labels.select("doc_id", F.col("toxic").cast("int").alias("toxic")).filter(F.col("toxic").isNotNull() & F.col("doc_id").isNotNull() & ~held_out())
    chosen = sample_ids(chosen.groupBy("doc_id").agg(F.max("toxic").alias("toxic")), sample).select("doc_id", "toxic")
    chosen = docs.sparkSession.createDataFrame([tuple(r) for r in chosen.collect()], "doc_id long, toxic int")
    texts = documents_view(docs).join(F.broadcast(chosen), "doc_id").select("text", "toxic")

    n_toxic = texts.filter("toxic > 0").select("toxic").count()

    def presence(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        counts = np.zeros((2, 1 << BITS), np.int32)
        total = [0, 0]
        for batch in batches:
            for raw, y in byte_rows(batch, ["text", "toxic"]):
                counts[int(y > 0)][np.unique(features((raw or b"").decode())[0])] += 1
                total[y > 0] += 1
        at = np.flatnonzero(counts.any(axis=0))
        yield pa.RecordBatch.from_arrays([pa.array(np.append(at, -1)), pa.array(np.append(counts[0][at], total[0]).astype(np.int64)), pa.array(np.append(counts[1][at], total[1]).astype(np.int64))], ["feature", "clean", "toxic"])

    lean = texts.mapInArrow(presence, "feature long, clean long, toxic long").groupBy("feature").agg(F.sum("clean").alias("clean"), F.sum("toxic").alias("toxic"))
    found = lean.filter((F.col("feature") == -1) | (F.col("toxic") >= max(1, min(3, n_toxic)))).toArrow()  # at most 2^20 rows
    f, b, a = (found.column(c).to_numpy().astype(float) for c in ("feature", "clean", "toxic"))
    n0, n1 = (float(x[f == -1][0]) if (f == -1).any() else 0.0 for x in (b, a))
    b, a, f = b[f >= 0], a[f >= 0], f[f >= 0].astype(np.int64)
    weights = np.zeros(1 << BITS)
    if not n0 or not n1 or not len(f):
        return MilModel(weights, NO_EVIDENCE)
    odds = np.log((a + 0.5) / (n1 - a + 0.5)) - np.log((b + 0.5) / (n0 - b + 0.5))
    lift = odds / np.sqrt(1 / (a + 0.5) + 1 / (n1 - a + 0.5) + 1 / (b + 0.5) + 1 / (n0 - b + 0.5))
    order = np.lexsort((f, -lift))[:most_features]
    enough = min(least_lift, 0.7 * lift.max()) if lift.max() > 0 else np.inf
    kept = np.sort(f[order[lift[order] >= enough]])

    def bags(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in batches:
            out = []
            for raw, y in byte_rows(batch, ["text", "toxic"]):
                g, where, n = features((raw or b"").decode())
                at = np.minimum(kept.searchsorted(g), len(kept) - 1)
                own = kept[at] == g
                pairs = np.unique(np.stack([where[own].astype(np.int32), at[own].astype(np.int32)]), axis=1)
                out.append((int(y > 0), n, pairs[0].tobytes(), pairs[1].tobytes()))
            cols = list(zip(*out)) or [()] * 4
            yield pa.RecordBatch.from_arrays([pa.array(c, t) for c, t in zip(cols, (pa.int32(), pa.int32(), pa.binary(), pa.binary()))], ["label", "n", "sentences", "features"])

    if not len(kept):
        return MilModel(weights, NO_EVIDENCE)
    got = texts.mapInArrow(bags, "label int, n int, sentences binary, features binary").toArrow().to_pylist()
    rows = [(r["label"], r["n"], np.frombuffer(r["sentences"], np.int32), np.frombuffer(r["features"], np.int32)) for r in got]
    w, bias = _fit(sorted(rows, key=lambda r: (r[0], r[1], r[3].tobytes(), r[2].tobytes())), len(kept))
    weights[kept] = w
    return MilModel(weights, bias)


def score(docs: DataFrame, model: MilModel, id_col: str = "doc_id", text_col: str = "text", threshold: float = 0.3) -> DataFrame:
    """One row per input row: doc_id, score, predicted, n_flagged and worst, the most toxic sentence's text.

    n_flagged counts sentences whose own score reaches ``threshold``.  Null and blank texts score 0
    and have no worst sentence.
    """
    known = docs.sparkSession.sparkContext.broadcast(model)

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in batches:
            out = []
            for doc_id, raw in byte_rows(batch, ["doc_id", "text"]):
                text = (raw or b"").decode()
                p = known.value.sentence_scores(text)
                flagged = int((p >= threshold).sum())
                worst = sentences(text)[int(p.argmax())] if flagged else None
                out.append((doc_id, s := noisy_or(p), int(s >= threshold), flagged, worst))
            cols = list(zip(*out)) or [()] * 5
            yield pa.RecordBatch.from_arrays([pa.array(c, t) for c, t in zip(cols, (pa.int64(), pa.float64(), pa.int32(), pa.int32(), pa.string()))], ["doc_id", "score", "predicted", "n_flagged", "worst"])

    return documents_view(docs, id_col, text_col).mapInArrow(run, "doc_id long, score double, predicted int, n_flagged int, worst string")


def keep_harmless(docs: DataFrame, model: MilModel, text_col: str = "text", threshold: float = 0.3) -> DataFrame:
    """The rows of ``docs``, with all columns, that score below ``threshold``; each row is judged by its own text."""
    known = docs.sparkSession.sparkContext.broadcast(model)
    return keep_rows(docs, lambda raw: known.value.score((raw or b"").decode()) < threshold, text_col)


def sentences(text: str) -> list[str]:
    """The sentences of a text in the order in which ``features`` numbers them."""
    out, last = [], 0
    for i, c in enumerate(text):
        if c in ".!?\n":
            out.append(text[last : i + 1])
            last = i + 1
    return [*out, text[last:]]


def op9_toxicity(spark: SparkSession, sf_dir: str) -> DataFrame:
    docs = spark.read.parquet(f"{sf_dir}/documents.parquet")
    model = train(docs, spark.read.parquet(f"{sf_dir}/labels.parquet"))
    return score(docs, model).select("doc_id", held_out().alias("held_out"), "score", "predicted", "n_flagged")
