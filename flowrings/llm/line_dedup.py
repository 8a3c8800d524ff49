"""Line deduplication with two Bloom filters.

One filter holds every line key that was seen, the other those seen in a second document: when the
filters of two tasks meet, bits set in both pass to the second one, which so misses no repeat.  Only
keys that the second filter lets through are shuffled, and counted exactly by a 128-bit digest.
The filters have some ``_BITS`` bits for each line (lines are counted first), are built in slices by a
shuffle, and only the second is sent to the tasks.  Beyond ``most_log2_bits`` bits it is not sent at all:
the digests go to the slices, each slice builds its own two filters and tests what it was given.  A filter
that is too small lets more keys through to the exact count, never fewer.
"""

from __future__ import annotations

import hashlib
from collections.abc import Iterator

import numpy as np
import pyarrow as pa
import xxhash
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from flowrings.llm.arrow import byte_rows, documents_view
from flowrings.llm.rolling import pack, unpack
from flowrings.scratch import materialize

_SLICE = 16  # log2 of the bits in a slice: positions within one fit 16 bits
_BITS, _LEAST_LOG2 = 8, 20
#: Lines for each slice where digests go to the slices.
_SLICE_LINES = 1_000_000


def line_key(line: bytes) -> bytes:
    return line.strip().lower()


def keys_of(raw: bytes, least: int) -> set[bytes]:
    """The distinct keys of a text that have at least ``least`` code points."""
    keys = {k for x in raw.split(b"\n") if len(k := line_key(x)) >= least}
    return {k for k in keys if k.isascii() or len(k.decode()) >= least}


def positions(hashes: np.ndarray, log2_bits: int) -> np.ndarray:
    """Two filter positions for each 64-bit hash: shape (2, n)."""
    return np.stack([hashes >> np.uint64(64 - log2_bits), hashes & np.uint64((1 << log2_bits) - 1)]).astype(np.int64)


def _hashes(keys: list[bytes]) -> np.ndarray:
    return np.fromiter(map(xxhash.xxh3_64_intdigest, keys), np.uint64, len(keys))


def _slices(at: np.ndarray) -> dict[int, np.ndarray]:
    """Distinct positions by slice, as 16-bit numbers."""
    at = np.unique(at)
    which = at >> _SLICE
    cuts = np.flatnonzero(np.diff(which)) + 1
    return {int(p[0] >> _SLICE): (p & ((1 << _SLICE) - 1)).astype(np.uint16) for p in np.split(at, cuts) if len(p)}


def twice_filter(view: DataFrame, least: int, log2_bits: int) -> np.ndarray:
    """The filter of keys seen in two documents, as packed bits."""

    def local(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in batches:
            parts = [_hashes(list(keys)) for _, raw in byte_rows(batch, ["doc_id", "text"]) if raw and (keys := keys_of(raw, least))]
            if not parts:
                continue
            h, n = np.unique(np.concatenate(parts), return_counts=True)
            once, twice = _slices(positions(h, log2_bits).ravel()), _slices(positions(h[n > 1], log2_bits).ravel())
            none = np.empty(0, np.uint16)
            rows = [(k, v.tobytes(), twice.get(k, none).tobytes()) for k, v in once.items()]
            yield pa.RecordBatch.from_arrays([pa.array(c, t) for c, t in zip(zip(*rows), (pa.int32(), pa.binary(), pa.binary()))], ["slice", "once", "twice"])

    def merge(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        now, once, twice = None, None, None

        def done():
            return pa.RecordBatch.from_arrays([pa.array([now], pa.int32()), pa.array([np.packbits(twice, bitorder="little").tobytes()], pa.binary())], ["slice", "bits"])

        for batch in batches:
            for k, a, b in byte_rows(batch, ["slice", "once", "twice"]):
                if k != now:
                    if now is not None and twice.any():
                        yield done()
                    now, once, twice = k, np.zeros(1 << _SLICE, bool), np.zeros(1 << _SLICE, bool)
                a = np.frombuffer(a, np.uint16)
                twice[a[once[a]]] = True
                twice[np.frombuffer(b, np.uint16)] = True
                once[a] = True
        if now is not None and twice.any():
            yield done()

    parts = view.mapInArrow(local, "slice int, once binary, twice binary").repartition("slice").sortWithinPartitions("slice")
    found = np.zeros(1 << (log2_bits - 3), np.uint8)
    for row in parts.mapInArrow(merge, "slice int, bits binary").toLocalIterator():
        start = row["slice"] << (_SLICE - 3)
        found[start : start + (1 << (_SLICE - 3))] = np.frombuffer(row["bits"], np.uint8)
    return found


def count_lines(view: DataFrame) -> int:
    """Lines of all texts, by built-in functions."""
    breaks = F.length("text") - F.length(F.replace("text", F.lit("\n"), F.lit("")))
    return view.agg(F.coalesce(F.sum(1 + breaks), F.lit(0))).first()[0]


def sent_suspects(view: DataFrame, least: int, log2_bits: int) -> DataFrame:
    """(doc_id, hi, lo): keys that the second filter, sent to all tasks, lets through."""
    known = view.sparkSession.sparkContext.broadcast(twice_filter(view, least, log2_bits))

    def suspects(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        bits = known.value
        for batch in batches:
            ids, digests = [], []
            for doc_id, raw in byte_rows(batch, ["doc_id", "text"]):
                keys = list(keys_of(raw or b"", least))
                p = positions(_hashes(keys), log2_bits)
                both = (bits[p >> 3] >> (p & 7).astype(np.uint8) & 1).all(axis=0)
                for i in np.flatnonzero(both).tolist():
                    ids.append(doc_id)
                    digests.append(xxhash.xxh3_128_digest(keys[i]))
            d = np.frombuffer(b"".join(digests), np.int64).reshape(-1, 2)
            yield pa.RecordBatch.from_arrays([pa.array(ids, pa.int64()), pa.array(d[:, 0]), pa.array(d[:, 1])], ["doc_id", "hi", "lo"])

    return view.mapInArrow(suspects, "doc_id long, hi long, lo long")


def sliced_suspects(view: DataFrame, least: int, slices: int) -> DataFrame:
    """The same from filters that stay in their slices: digests of all lines are shuffled once, as sorted blocks.

    Of a key that several documents of a batch have, one row goes to its slice; the others are suspects
    already and pass in blocks dealt out evenly, so a line of a third of all documents fills no slice.
    """

    def deal(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in batches:
            digests, ids, blank = [], [], []
            for doc_id, raw in byte_rows(batch, ["doc_id", "text"]):
                keys = keys_of(raw or b"", least)
                digests += map(xxhash.xxh3_128_digest, keys)
                ids += [doc_id or 0] * len(keys)
                blank += [doc_id is None] * len(keys)
            if not ids:
                continue
            d = np.frombuffer(b"".join(digests), np.uint64).reshape(-1, 2)
            ids, blank = np.array(ids, np.int64), np.array(blank, np.int64)
            order = np.lexsort((d[:, 1], d[:, 0]))
            hi, lo, ids, blank = d[order, 0], d[order, 1].view(np.int64), ids[order], blank[order]
            first = np.append(True, (hi[1:] != hi[:-1]) | (lo[1:] != lo[:-1]))
            several = (np.bincount(np.cumsum(first) - 1)[np.cumsum(first) - 1] > 1).astype(np.int64)
            home, rows = (hi % np.uint64(slices)).astype(np.int32), []
            at = np.flatnonzero(first)
            at = at[np.argsort(home[at], kind="stable")]
            for p in np.split(at, np.flatnonzero(np.diff(home[at])) + 1):
                rows.append((int(home[p[0]]), 0, pack(hi[p], lo[p], ids[p], blank[p], several[p])))
            rest = np.flatnonzero(~first)
            if len(rest):
                rows.append((int(home[rest[len(rest) // 2]]), 1, pack(hi[rest], lo[rest], ids[rest], blank[rest], several[rest])))
            yield pa.RecordBatch.from_arrays([pa.array(c, t) for c, t in zip(zip(*rows), (pa.int32(), pa.int32(), pa.binary()))], ["slice", "kind", "block"])

    def rows(hi, lo, ids, blank, own):
        return pa.RecordBatch.from_arrays([pa.array(ids[own], mask=blank[own] > 0), pa.array(hi[own].view(np.int64)), pa.array(lo[own])], ["doc_id", "hi", "lo"])

    def tested(blocks: list[bytes]) -> Iterator[pa.RecordBatch]:
        """The two filters of a slice from its blocks, then the blocks against the second."""
        size = 1 << max(10, (_BITS * sum(len(unpack(b, 5)[0]) for b in blocks)).bit_length())
        once, twice = np.zeros(size, bool), np.zeros(size, bool)
        place = lambda hi, lo: np.stack([lo.view(np.uint64), hi // np.uint64(slices)]) % np.uint64(size)
        for block in blocks:
            hi, lo, _, _, several = unpack(block, 5)
            p = place(hi, lo)
            seen = p[once[p]]
            twice[seen], twice[p[:, several > 0]] = True, True
            once[p] = True
        for block in blocks:
            hi, lo, ids, blank, _ = unpack(block, 5)
            yield rows(hi, lo, ids, blank, twice[place(hi, lo)].all(axis=0))

    def test(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        now, blocks = None, []
        for batch in batches:
            for key, kind, block in byte_rows(batch, ["slice", "kind", "block"]):
                if key != now:
                    yield from tested(blocks)
                    now, blocks = key, []
                if kind == 0:
                    blocks.append(block)
                else:
                    hi, lo, ids, blank, _ = unpack(block, 5)
                    yield rows(hi, lo, ids, blank, np.ones(len(hi), bool))
        yield from tested(blocks)

    dealt = view.mapInArrow(deal, "slice int, kind int, block binary").repartition("slice").sortWithinPartitions("slice", "kind")
    return dealt.mapInArrow(test, "doc_id long, hi long, lo long")


def repeated_lines(view: DataFrame, least: int, min_docs: int, most_log2_bits: int) -> DataFrame:
    """(doc_id, hi, lo): digests of keys that this document must lose."""
    n = count_lines(view)
    log2_bits = max(_LEAST_LOG2, (_BITS * n).bit_length())
    suspects = sent_suspects(view, least, log2_bits) if log2_bits <= most_log2_bits else sliced_suspects(view, least, 1 + n // _SLICE_LINES)
    found = materialize(suspects, "suspect-lines")
    confirmed = found.groupBy("hi", "lo").agg(F.count(F.lit(1)).alias("n"), F.max("doc_id").alias("keeper")).filter(F.col("n") >= min_docs)
    return found.join(materialize(confirmed.drop("n"), "repeated-lines"), ["hi", "lo"]).filter(~F.col("doc_id").eqNullSafe(F.col("keeper"))).select("doc_id", "hi", "lo")


def drop_repeated_lines(
    docs: DataFrame, id_col: str = "doc_id", text_col: str = "text", *, least: int = 20, min_docs: int = 3, most_log2_bits: int = 28
) -> DataFrame:
    """One row per input row: doc_id, n_lines, n_dropped, kept_sha256, kept (the text that remains).

    A line's key is the line without ASCII white space at its ends, A-Z lower-cased.  Keys of at least
    ``least`` code points in at least ``min_docs`` rows lose all their lines except in the row of the
    largest doc_id that has them.  Null and empty texts are one empty line.  Rows that repeat a doc_id
    count as documents of their own; they lose or keep lines alike.  Rows with a null doc_id count, too,
    and keep their lines.  ``most_log2_bits`` bounds the filter that is sent to the tasks (2^28 bits: 32 MB).
    """
    view = documents_view(docs, id_col, text_col)
    drops = repeated_lines(view, least, min_docs, most_log2_bits).groupBy("doc_id").agg(
        F.collect_set(F.struct("hi", "lo")).alias("drops")
    )

    def finish(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in batches:
            out = []
            drops = batch.column(batch.schema.get_field_index("drops"))
            for i, (doc_id, raw) in enumerate(byte_rows(batch, ["doc_id", "text"])):
                lines = (raw or b"").split(b"\n")
                kept = lines
                if drops[i].is_valid:
                    gone = {np.array([x["hi"], x["lo"]], np.int64).tobytes() for x in drops[i].as_py()}
                    kept = [x for x in lines if not (len(k := line_key(x)) >= least and xxhash.xxh3_128_digest(k) in gone)]
                text = b"\n".join(kept)
                out.append((doc_id, len(lines), len(lines) - len(kept), hashlib.sha256(text).hexdigest(), text.decode()))
            cols = list(zip(*out)) or [()] * 5
            yield pa.RecordBatch.from_arrays([pa.array(c, t) for c, t in zip(cols, (pa.int64(), pa.int64(), pa.int64(), pa.string(), pa.string()))], ["doc_id", "n_lines", "n_dropped", "kept_sha256", "kept"])

    return view.join(drops, "doc_id", "left").mapInArrow(finish, "doc_id long, n_lines long, n_dropped long, kept_sha256 string, kept string")


def op3_line_dedup(spark: SparkSession, sf_dir: str) -> DataFrame:
    return drop_repeated_lines(spark.read.parquet(f"{sf_dir}/documents.parquet")).drop("kept")


ORACLE = r"""
WITH l AS (SELECT doc_id, unnest(string_split(coalesce(text, ''), chr(10))) AS line, generate_subscripts(string_split(coalesce(text, ''), chr(10)), 1) AS p FROM documents),
k AS (SELECT *, translate(trim(line, chr(32) || chr(9) || chr(10) || chr(11) || chr(12) || chr(13)), 'ABCDEFGHIJKLMNOPQRSTUVWXYZ', 'abcdefghijklmnopqrstuvwxyz') AS key FROM l),
r AS (SELECT key, max(doc_id) AS keeper FROM k WHERE length(key) >= 20 GROUP BY key HAVING count(DISTINCT doc_id) >= 3),
f AS (SELECT k.doc_id, p, line, keeper IS NOT NULL AND k.doc_id <> keeper AS gone FROM k LEFT JOIN r USING (key))
SELECT doc_id, count(*) AS n_lines, count(*) FILTER (gone) AS n_dropped,
       sha256(coalesce(string_agg(line, chr(10) ORDER BY p) FILTER (NOT gone), '')) AS kept_sha256
FROM f GROUP BY doc_id
"""
