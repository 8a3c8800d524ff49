"""Benchmark decontamination by winnowed fingerprints.

A window is 13 consecutive words of a benchmark item (a shorter item is one window).  Among the
k-grams of every window the least hash is kept; a text that contains the window keeps the same
k-gram, so joining the kept hashes misses no occurrence.  Each hit is extended to whole windows, which
are compared by 128-bit digests of their word hashes.  Items of one length class share k and the window size.
"""

from __future__ import annotations

import hashlib
from collections.abc import Iterator

import numpy as np
import pyarrow as pa
import xxhash
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from flowrings.llm.arrow import byte_rows, documents_view, keep_rows
from flowrings.llm.rolling import grams, sliding_min
from flowrings.scratch import materialize

# Bytes that end a word; A-Z become a-z; digits, letters and all bytes from 0x80 on are word bytes.
_FOLD = bytes(c + 32 if 65 <= c <= 90 else c if 48 <= c <= 57 or 97 <= c <= 122 or c >= 128 else 32 for c in range(256))
#: Bytes of an index for each byte of benchmark text at most: 32 a word, which takes two bytes at least.
_EXPANDED = 16


def word_hashes(raw: bytes) -> np.ndarray:
    words = raw.translate(_FOLD).split()
    return np.fromiter(map(xxhash.xxh3_64_intdigest, words), np.uint64, len(words))


def shape(length: int, k: int) -> tuple[int, int]:
    """For windows of ``length`` words: words in a k-gram, k-grams in a window."""
    k = min(k, length)
    return k, length - k + 1


def digests(a: np.ndarray, starts: list[int] | range, length: int) -> np.ndarray:
    """(n, 2): the 128-bit digest of the window of ``length`` word hashes at each start."""
    raw, wide = a.tobytes(), 8 * length
    return np.frombuffer(b"".join([xxhash.xxh3_128_digest(raw[8 * s : 8 * s + wide]) for s in starts]), np.uint64).reshape(-1, 2)


class Fingerprints:
    """Winnowed fingerprints of some items and the digests of their windows, as sorted arrays by window length.

    24 bytes a distinct window and item, and 8 a fingerprint: small enough to send to every task where
    the benchmark's text is (see ``decontaminate``).
    """

    def __init__(self, items: list[tuple[str, bytes]], window: int, k: int):
        self.k, self.ids, by_length = k, [x for x, _ in items], {}
        for i, (_, raw) in enumerate(items):
            a = word_hashes(raw or b"")
            if len(a):
                length = min(window, len(a))
                kk, w = shape(length, k)
                kept, both, who = by_length.setdefault(length, ([], [], []))
                kept.append(np.unique(sliding_min(grams(a, kk), w)))
                both.append(digests(a, range(len(a) - length + 1), length))
                who.append(np.full(len(both[-1]), i, np.int32))
        self.tables = {}
        for length, (kept, both, who) in by_length.items():
            d, who = np.concatenate(both), np.concatenate(who)
            order = np.lexsort((who, d[:, 1], d[:, 0]))
            d, who = d[order], who[order]
            new = np.append(True, (d[1:] != d[:-1]).any(axis=1))
            first = np.flatnonzero(new)
            self.tables[length] = (np.unique(np.concatenate(kept)), d[first, 0].copy(), d[first, 1].copy(), np.append(first, len(d)).astype(np.int32), who)

    def search(self, raw: bytes) -> tuple[int, int, set[int]]:
        """Words, hit words and items with occurring windows of one document."""
        a = word_hashes(raw)
        edges, found = None, set()
        for length, (kept, high, low, first, who) in self.tables.items():
            k, w = shape(length, self.k)
            least = sliding_min(grams(a, k), w)
            if not len(least):
                continue
            at = kept.searchsorted(least)
            starts = np.flatnonzero(kept[np.minimum(at, len(kept) - 1)] == least)
            if not len(starts):
                continue
            d = digests(a, starts.tolist(), length)
            at, last = high.searchsorted(d[:, 0]), len(high) - 1
            # windows that share half a digest stand side by side
            while (step := (at < last) & (high[np.minimum(at, last)] == d[:, 0]) & (low[np.minimum(at, last)] < d[:, 1])).any():
                at += step
            at = np.minimum(at, last)
            same = (high[at] == d[:, 0]) & (low[at] == d[:, 1])
            if same.any():
                edges = np.zeros(len(a) + 1, np.int64) if edges is None else edges
                np.add.at(edges, starts[same], 1)
                np.add.at(edges, starts[same] + length, -1)
                for g in np.unique(at[same]).tolist():
                    found.update(who[first[g] : first[g + 1]].tolist())
        return len(a), 0 if edges is None else int((edges.cumsum() > 0).sum()), found


_SCHEMA = "doc_id long, n_words long, n_hit long, n_items long, items_sha256 string, contaminated boolean"


def _verdict(doc_id, n, hit, items, share):
    return doc_id, n, hit, len(items), hashlib.sha256(",".join(sorted(items)).encode()).hexdigest(), hit > 0 and share * hit >= n


def _items(bench: DataFrame, item_col: str, item_text: str) -> DataFrame:
    return bench.select(F.coalesce(F.col(f"`{item_col}`").cast("string"), F.lit("")).alias("item_id"), F.coalesce(F.col(f"`{item_text}`"), F.lit("")).alias("item_text"))


def _small_index(items: DataFrame, window: int, k: int, most: int) -> Fingerprints | None:
    """The fingerprints of all items, or None where they could take more than ``most`` bytes."""
    total = items.agg(F.coalesce(F.sum(_EXPANDED * F.octet_length("item_text") + 64), F.lit(0))).first()[0]
    return None if total > most else Fingerprints([(r[0], r[1].encode()) for r in items.collect()], window, k)


def decontaminate(
    docs: DataFrame, bench: DataFrame, *, id_col: str = "doc_id", text_col: str = "text", item_col: str = "item_id",
    item_text: str = "text", window: int = 13, k: int = 5, share: int = 20, broadcast_bytes: int = 128 << 20,
) -> DataFrame:
    """One row per input row: doc_id, n_words, n_hit, n_items, items_sha256, contaminated.

    A document is contaminated if it has a hit word and ``share`` times its hit words are at least
    its words.  Null and empty texts (of documents or items) have no words.  Repeated items count
    once per item_id; a null item_id shows as an empty string.  If the benchmark's index could take more
    than ``broadcast_bytes``, fingerprints are joined by a shuffle instead of being sent to the tasks.  Each
    row is judged by its own text, also where its doc_id is null or repeated.
    """
    view, items = documents_view(docs, id_col, text_col), _items(bench, item_col, item_text)
    index = _small_index(items, window, k, broadcast_bytes)
    if index is None:
        return _by_shuffle(view, items, window, k, share)
    known = view.sparkSession.sparkContext.broadcast(index)

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        index = known.value
        for batch in batches:
            out = []
            for doc_id, raw in byte_rows(batch, ["doc_id", "text"]):
                n, hit, found = index.search(raw or b"")
                out.append(_verdict(doc_id, n, hit, {index.ids[i] for i in found}, share))
            yield _record(out)

    return view.mapInArrow(run, _SCHEMA)


def keep_clean(
    docs: DataFrame, bench: DataFrame, *, text_col: str = "text", item_col: str = "item_id", item_text: str = "text",
    window: int = 13, k: int = 5, share: int = 20, broadcast_bytes: int = 128 << 20,
) -> DataFrame:
    """The rows of ``docs``, with all columns, that ``decontaminate`` calls clean; each is judged by its own text."""
    index = _small_index(_items(bench, item_col, item_text), window, k, broadcast_bytes)
    if index is not None:
        known = docs.sparkSession.sparkContext.broadcast(index)

        def clean(raw: bytes | None) -> bool:
            n, hit, _ = known.value.search(raw or b"")
            return not (hit > 0 and share * hit >= n)

        return keep_rows(docs, clean, text_col)
    keyed = materialize(docs.withColumn("__row", F.monotonically_increasing_id()), "numbered")
    judged = decontaminate(keyed, bench, id_col="__row", text_col=text_col, item_col=item_col, item_text=item_text, window=window, k=k, share=share, broadcast_bytes=-1)
    bad = materialize(judged.filter("contaminated").select(F.col("doc_id").alias("__row")), "contaminated")
    return keyed.join(bad, "__row", "left_anti").drop("__row")


def _record(rows: list[tuple]) -> pa.RecordBatch:
    cols = list(zip(*rows)) or [()] * 6
    types = [pa.int64()] * 4 + [pa.string(), pa.bool_()]
    return pa.RecordBatch.from_arrays([pa.array(c, t) for c, t in zip(cols, types)], [x.split()[0] for x in _SCHEMA.split(", ")])


def _by_shuffle(view: DataFrame, items: DataFrame, window: int, k: int, share: int) -> DataFrame:
    """The same result where the benchmark is too large to send: fingerprints, then digests, meet in joins.

    A document's fingerprints are joined with the distinct ones of the benchmark; only windows at those
    that meet become digests, which are joined with the distinct digests of the items.  No text meets a
    second text, no list grows beyond what one document holds, and a fingerprint of a third of all
    documents is a skewed join side, which adaptive execution splits.  Rows meet by a number of their own.
    """
    view = materialize(view.withColumn("row", F.monotonically_increasing_id()), "numbered")

    def item_windows(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in batches:
            for item_id, raw in byte_rows(batch, ["item_id", "item_text"]):
                a = word_hashes(raw or b"")
                if not len(a):
                    continue
                length = min(window, len(a))
                kk, w = shape(length, k)
                least, d, n = sliding_min(grams(a, kk), w), digests(a, range(len(a) - length + 1), length), len(a) - length + 1
                cols = [pa.array([item_id.decode()] * n), pa.array([length] * n, pa.int32()), *(pa.array(x.view(np.int64)) for x in (least, d[:, 0].copy(), d[:, 1].copy()))]
                yield pa.RecordBatch.from_arrays(cols, ["item_id", "length", "h", "hi", "lo"])

    known = materialize(items.mapInArrow(item_windows, "item_id string, length int, h long, hi long, lo long").distinct(), "item-windows")
    lengths = sorted(r[0] for r in known.select("length").distinct().collect())  # at most ``window`` numbers

    def marks(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in batches:
            ids, n_words, ends, of, hs = [], [], [0], [], []
            for row, doc_id, raw in byte_rows(batch, ["row", "doc_id", "text"]):
                a = word_hashes(raw or b"")
                ids.append((row, doc_id))
                n_words.append(len(a))
                for length in lengths:
                    kk, w = shape(length, k)
                    hs.append(np.unique(sliding_min(grams(a, kk), w)))
                    of.append(np.full(len(hs[-1]), length, np.int32))
                ends.append(ends[-1] + sum(map(len, hs[len(hs) - len(lengths) :])))
            none = np.empty(0, np.uint64)
            prints = pa.StructArray.from_arrays([pa.array(np.concatenate([none.astype(np.int32), *of])), pa.array(np.concatenate([none, *hs]).view(np.int64))], ["length", "h"])
            rows, docs = zip(*ids) if ids else ((), ())
            yield pa.RecordBatch.from_arrays([pa.array(rows, pa.int64()), pa.array(docs, pa.int64()), pa.array(n_words, pa.int64()), pa.ListArray.from_arrays(pa.array(ends, pa.int32()), prints)], ["row", "doc_id", "n_words", "prints"])

    marked = materialize(view.mapInArrow(marks, "row long, doc_id long, n_words long, prints array<struct<length: int, h: long>>"), "marked")
    wanted = known.select("length", "h").distinct()
    met = marked.select("row", F.explode("prints").alias("x")).select("row", "x.length", "x.h").join(wanted, ["length", "h"], "left_semi")
    met = met.groupBy("row").agg(F.collect_set(F.struct("length", "h")).alias("met"))

    def occurrences(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in batches:
            out = []
            for row, raw, met in byte_rows(batch, ["row", "text", "met"]):
                a, by = word_hashes(raw or b""), {}
                for x in met:
                    by.setdefault(x["length"], []).append(x["h"])
                for length, hs in by.items():
                    kk, w = shape(length, k)
                    starts = np.flatnonzero(np.isin(sliding_min(grams(a, kk), w).view(np.int64), hs)).tolist()
                    same: dict[tuple[int, int], list[int]] = {}
                    for s, (hi, lo) in zip(starts, digests(a, starts, length).view(np.int64).tolist()):
                        same.setdefault((hi, lo), []).append(s)
                    out += [(row, length, hi, lo, at) for (hi, lo), at in same.items()]
            cols = list(zip(*out)) or [()] * 5
            yield pa.RecordBatch.from_arrays([pa.array(c, t) for c, t in zip(cols, (pa.int64(), pa.int32(), pa.int64(), pa.int64(), pa.list_(pa.int32())))], ["row", "length", "hi", "lo", "starts"])

    found = materialize(view.join(met, "row").select("row", "text", "met").mapInArrow(occurrences, "row long, length int, hi long, lo long, starts array<int>"), "occurrences")
    spans = found.join(known.select("hi", "lo").distinct(), ["hi", "lo"], "left_semi").groupBy("row").agg(F.collect_list(F.struct("starts", "length")).alias("spans"))
    owners = found.select("row", "hi", "lo").join(known.select("hi", "lo", "item_id").distinct(), ["hi", "lo"]).groupBy("row").agg(F.collect_set("item_id").alias("items"))

    def finish(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in batches:
            out = []
            for doc_id, n, found, spans in byte_rows(batch, ["doc_id", "n_words", "items", "spans"]):
                hit = np.zeros(n, bool)
                for x in spans or ():
                    for s in x["starts"]:
                        hit[s : s + x["length"]] = True
                out.append(_verdict(doc_id, n, int(hit.sum()), set(found or ()), share))
            yield _record(out)

    judged = marked.select("row", "doc_id", "n_words").join(owners, "row", "left").join(spans, "row", "left")
    return judged.select("doc_id", "n_words", "items", "spans").mapInArrow(finish, _SCHEMA)


def op10_decontaminate(spark: SparkSession, sf_dir: str) -> DataFrame:
    return decontaminate(spark.read.parquet(f"{sf_dir}/documents.parquet"), spark.read.parquet(f"{sf_dir}/benchmark.parquet"))


_WORDS = r"regexp_extract_all(regexp_replace(translate(coalesce(text, ''), 'ABCDEFGHIJKLMNOPQRSTUVWXYZ', 'abcdefghijklmnopqrstuvwxyz'), '[\x00-\x2F\x3A-\x60\x7B-\x7F]+', ' ', 'g'), '[^ ]+')"
ORACLE = rf"""
WITH d AS (SELECT doc_id, {_WORDS} AS w FROM documents),
b AS (SELECT CAST(item_id AS VARCHAR) AS item_id, {_WORDS} AS w FROM benchmark),
bw AS (SELECT DISTINCT item_id, least(13, len(w)) AS n, array_to_string(w[i : i + least(13, len(w)) - 1], ' ') AS win
       FROM b, unnest(generate_series(1, len(w) - least(13, len(w)) + 1)) AS t(i) WHERE len(w) > 0),
lens AS (SELECT DISTINCT n FROM bw),
dw AS (SELECT doc_id, n, i, array_to_string(w[i : i + n - 1], ' ') AS win
       FROM d, lens, unnest(generate_series(1, len(w) - n + 1)) AS t(i) WHERE len(w) >= n),
hits AS (SELECT doc_id, dw.n, i, item_id FROM dw JOIN bw ON dw.n = bw.n AND dw.win = bw.win),
words AS (SELECT doc_id, count(DISTINCT p) AS n_hit FROM (SELECT doc_id, unnest(generate_series(i, i + n - 1)) AS p FROM hits) GROUP BY 1),
items AS (SELECT doc_id, count(*) AS n_items, string_agg(item_id, ',' ORDER BY item_id) AS ids FROM (SELECT DISTINCT doc_id, item_id FROM hits) GROUP BY 1)
SELECT doc_id, CAST(len(w) AS BIGINT) AS n_words, coalesce(n_hit, 0) AS n_hit, coalesce(n_items, 0) AS n_items,
       sha256(coalesce(ids, '')) AS items_sha256, coalesce(n_hit, 0) > 0 AND 20 * coalesce(n_hit, 0) >= len(w) AS contaminated
FROM d LEFT JOIN words USING (doc_id) LEFT JOIN items USING (doc_id)
"""
