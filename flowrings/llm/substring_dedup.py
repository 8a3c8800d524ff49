"""Substring deduplication with a log-structured index of window fingerprints.

A window is 13 consecutive words.  Its fingerprint is the least hash among its 5-word runs, so equal
windows have equal fingerprints and neighbouring windows mostly share one: the index is several times
smaller than the list of windows.  The index is a set of immutable runs; a run holds, slice by slice of
the hash space, sorted postings (fingerprint, document).  A new batch is turned into sorted blocks, the
blocks of a slice are merged with each other and with the runs, and fingerprints that meet in two
documents mark their windows as suspects.  Suspect windows are then verified by 128-bit digests of their
words (two independent 64-bit halves); the batch becomes a run, and runs are compacted by a streaming
merge, which also deals them out to more slices as the index grows.

Hot fingerprints: a task sends one posting per fingerprint (that of its smallest document) to the
merge; the others are known to repeat already and travel in blocks dealt out evenly, so a slice gets
at most one posting per task for any fingerprint.
"""

from __future__ import annotations

import hashlib
import uuid
from collections.abc import Callable, Iterator

import numpy as np
import pyarrow as pa
import xxhash
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from flowrings.llm.arrow import byte_rows, documents_view
from flowrings.llm.rolling import grams, pack, sliding_min, unpack
from flowrings.scratch import materialize, release_shuffles, scratch_path

_HEADS, _PAST, _TAILS = 0, 1, 2
_BLOCKS = "slice int, kind int, block binary"
#: A block of a run: its slice, its least fingerprint (``_ordered``) and its number of postings.
_RUN = "slice int, least long, n long, block binary"
_FLUSH, _CHUNK = 1_000_000, 10_000
#: Bytes of text whose words are hashed at once: arrays of some 200,000 words.
_TEXT_BYTES = 1 << 20
# Odd constants of the two word hashes, and masks for the first 0 to 8 bytes of a number.
_MIXES = tuple((np.uint64(c), np.uint64(e)) for c, e in ((0x9FB21C651E98DF25, 0xD6E8FEB86659FD93), (0xC2B2AE3D27D4EB4F, 0xFF51AFD7ED558CCD)))
_MASKS = np.array([(1 << 8 * i) - 1 for i in range(9)], np.uint64)
#: Longer words, in bytes, are hashed one by one.
_LONG_WORD = 64
#: Postings that a slice holds on average before compaction doubles the number of slices.
_SLICE_POSTINGS = 4_000_000
#: Suspect postings for each slice of the windows that are verified: some 100,000 windows, so that blocks stay large.
_SLICE_SUSPECTS = 20_000


class FingerprintIndex:
    """Runs of postings under ``path``; all runs have one number of slices, which compaction may double."""

    def __init__(self, spark: SparkSession, path: str, slices: int | None = None):
        self.spark, self.path = spark, path.rstrip("/")
        self._fs_path = spark._jvm.org.apache.hadoop.fs.Path
        self._fs = self._fs_path(self.path).getFileSystem(spark._jsc.hadoopConfiguration())
        names = self.runs()
        self.slices = int(names[0].rsplit("-", 1)[1]) if names else slices or int(spark.conf.get("spark.sql.shuffle.partitions"))

    def runs(self) -> list[str]:
        """Names of the runs, oldest first: run-<number>-<slices>."""
        if not self._fs.exists(self._fs_path(self.path)):
            return []
        return sorted(s.getPath().getName() for s in self._fs.listStatus(self._fs_path(self.path)) if s.getPath().getName().startswith("run-"))

    def next_run(self, slices: int) -> str:
        names = self.runs()
        return f"{self.path}/run-{int(names[-1].split('-')[1]) + 1 if names else 0:06d}-{slices}"

    def read(self) -> DataFrame | None:
        """(slice, least, n, block) of all runs."""
        names = self.runs()
        return self.spark.read.schema(_RUN).parquet(*(f"{self.path}/{n}" for n in names)) if names else None

    def commit(self, written: str, slices: int | None = None) -> None:
        """Turn a folder of blocks into the next run by renaming it; nothing happens if it does not exist."""
        if self._fs.exists(self._fs_path(written)):
            self._fs.mkdirs(self._fs_path(self.path))
            self._fs.rename(self._fs_path(written), self._fs_path(self.next_run(slices or self.slices)))

    def compact(self) -> None:
        """Merge all runs into one: one ascending sequence of blocks for each slice.

        A task merges the runs of a slice block by block and holds only blocks whose ranges overlap.
        """
        names = self.runs()
        if len(names) < 2:
            return
        total = self.read().agg(F.coalesce(F.sum("n"), F.lit(0))).first()[0]
        slices = self.slices
        while slices * _SLICE_POSTINGS < total:
            slices *= 2
        target, kept = scratch_path(self.spark, "compacted-run"), self.read()
        if slices != self.slices:
            kept = kept.select("block").mapInArrow(lambda batches: _dealt_again(batches, slices), _RUN)
        merged = kept.repartition("slice").sortWithinPartitions("slice", "least").mapInArrow(_merged_blocks, _RUN)
        merged.write.parquet(target)
        self.commit(target, slices)
        for n in names:
            self._fs.delete(self._fs_path(f"{self.path}/{n}"), True)
        self.slices = slices


def _ordered(h: np.ndarray) -> np.ndarray:
    """Unsigned numbers as signed ones in the same order."""
    return (h ^ np.uint64(1 << 63)).view(np.int64)


def _run_rows(rows: list[tuple[int, np.ndarray, np.ndarray]]) -> pa.RecordBatch:
    """Blocks of a run from (slice, ascending fingerprints, documents)."""
    cols = ([k for k, _, _ in rows], [int(_ordered(h[:1])[0]) for _, h, _ in rows], [len(h) for _, h, _ in rows], [pack(h, d) for _, h, d in rows])
    types = (pa.int32(), pa.int64(), pa.int64(), pa.binary())
    return pa.RecordBatch.from_arrays([pa.array(c, t) for c, t in zip(cols, types)], ["slice", "least", "n", "block"])


def _by_slice(h: np.ndarray, d: np.ndarray, slices: int) -> list[tuple[int, np.ndarray, np.ndarray]]:
    """Postings dealt out to their slices, in the order they have."""
    home = (h % np.uint64(slices)).astype(np.int32)
    order = np.argsort(home, kind="stable")
    return [(int(home[p[0]]), h[p], d[p]) for p in np.split(order, np.flatnonzero(np.diff(home[order])) + 1) if len(p)]


def _dealt_again(batches: Iterator[pa.RecordBatch], slices: int) -> Iterator[pa.RecordBatch]:
    for batch in batches:
        for (block,) in byte_rows(batch, ["block"]):
            yield _run_rows(_by_slice(*unpack(block, 2), slices))


def _merged_blocks(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
    """Blocks by (slice, least) as one ascending sequence a slice: what lies below the next block's least is final."""

    def cut(key, h, d, all_of_it):
        full = len(h) if all_of_it else len(h) // _CHUNK * _CHUNK
        if full:
            yield _run_rows([(key, h[i : min(i + _CHUNK, full)], d[i : min(i + _CHUNK, full)]) for i in range(0, full, _CHUNK)])
        return h[full:], d[full:]

    none = (np.empty(0, np.uint64), np.empty(0, np.int64))
    now, ready, waiting = None, none, none
    for batch in batches:
        for key, least, block in byte_rows(batch, ["slice", "least", "block"]):
            if key != now:
                if now is not None:
                    yield from cut(now, *(np.concatenate(x) for x in zip(ready, waiting)), True)
                now, ready, waiting = key, none, none
            split = int(_ordered(waiting[0]).searchsorted(least))
            ready = tuple(np.concatenate([r, w[:split]]) for r, w in zip(ready, waiting))
            h, d = (np.concatenate(x) for x in zip((w[split:] for w in waiting), unpack(block, 2)))
            order = np.lexsort((d, h))
            waiting = h[order], d[order]
            ready = yield from cut(now, *ready, False)
    if now is not None:
        yield from cut(now, *(np.concatenate(x) for x in zip(ready, waiting)), True)


def word_hashes(texts: pa.Array) -> tuple[np.ndarray, np.ndarray, np.ndarray]:
    """Of texts without nulls: where each one's words start (one bound more than texts), and both halves of the words' 128-bit hashes.

    All words are found and hashed at once, in rounds of 8 bytes.  In a round both halves take the bytes through
    one-to-one mixing with constants of their own, so words of one length up to 8 bytes never share a half.
    """
    ends = np.frombuffer(texts.buffers()[1], np.int32)[texts.offset : texts.offset + len(texts) + 1].astype(np.int64)
    size = int(ends[-1] - ends[0])
    raw = np.full(size + 8, 32, np.uint8)
    if size:
        raw[:size] = np.frombuffer(texts.buffers()[2], np.uint8)[ends[0] : ends[-1]]
    ends -= ends[0]
    edge = np.zeros(size + 1, bool)
    edge[ends] = True
    solid = (raw != 32) & ((raw < 9) | (raw > 13))
    start = np.flatnonzero(solid[:size] & (edge[:size] | ~np.append(False, solid[: max(size - 1, 0)])[:size]))
    n = np.flatnonzero(solid[:size] & (edge[1:] | ~solid[1 : size + 1])) + 1 - start
    eights = np.ndarray(size + 1, np.uint64, raw, strides=(1,))
    halves = [(n.astype(np.uint64) + np.uint64(1)) * c for c, _ in _MIXES]
    live, at = slice(None), start
    for done in range(0, _LONG_WORD, 8):
        if not len(at):
            break
        x = eights[at + done] & _MASKS[np.minimum(n[live] - done, 8)]
        for h, (c, e) in zip(halves, _MIXES):
            y = (h[live] ^ x) * c
            y ^= y >> np.uint64(32)
            y *= e
            y ^= y >> np.uint64(29)
            h[live] = y
        live = np.flatnonzero(n > done + 8) if done == 0 else live[n[live] > done + 8]
        at = start[live]
    for i in np.flatnonzero(n > _LONG_WORD).tolist():
        for h, x in zip(halves, np.frombuffer(xxhash.xxh3_128_digest(raw[start[i] : start[i] + n[i]].tobytes()), np.uint64)):
            h[i] = x
    return start.searchsorted(ends), *halves


def _few_texts(batches: Iterator[pa.RecordBatch], most: int = _TEXT_BYTES) -> Iterator[tuple[pa.RecordBatch, pa.Array]]:
    """Rows that have a doc_id, and their texts without nulls, in batches of some ``most`` bytes; a longer text is a batch of its own."""
    for batch in batches:
        named = batch.column(batch.schema.get_field_index("doc_id")).is_valid()
        batch = batch.filter(named) if named.false_count else batch
        texts = batch.column(batch.schema.get_field_index("text")).cast(pa.binary())
        texts = texts.fill_null(b"") if texts.null_count else texts
        if not len(texts):
            continue
        ends, start = np.frombuffer(texts.buffers()[1], np.int32)[texts.offset : texts.offset + len(texts) + 1], 0
        while start < len(texts):
            stop = max(start + 1, int(ends.searchsorted(int(ends[start]) + most, "right")) - 1)
            yield batch.slice(start, stop - start), texts.slice(start, stop - start)
            start = stop


def _window_runs(bounds: np.ndarray, a: np.ndarray, window: int, k: int) -> tuple[np.ndarray, np.ndarray, np.ndarray]:
    """Of the texts' windows: the first words of runs that share one fingerprint, these fingerprints, and the length of each run."""
    least = sliding_min(grams(a, k), window - k + 1)
    row = np.repeat(np.arange(len(bounds) - 1, dtype=np.int32), np.diff(bounds))
    row, inside = row[: len(least)], row[: len(least)] == row[window - 1 :]
    change = np.append(True, (least[1:] != least[:-1]) | (row[1:] != row[:-1]) | (inside[1:] != inside[:-1]))[: len(least)]
    first = np.flatnonzero(change)
    length = np.diff(np.append(first, len(least)))
    own = inside[first]
    return first[own], least[first[own]], length[own]


def _blocks(keys: np.ndarray, heads: np.ndarray, columns: list[np.ndarray], slices: int, salt: int) -> pa.RecordBatch:
    """Blocks of the entries of one task, sorted by key: heads to the slice of their key, tails to any slice."""
    rows = []
    where = (keys % np.uint64(slices)).astype(np.int32)
    at = np.flatnonzero(heads)
    at = at[np.argsort(where[at], kind="stable")]
    for part in np.split(at, np.flatnonzero(np.diff(where[at])) + 1):
        if len(part):
            rows.append((int(where[part[0]]), _HEADS, pack(keys[part], *(c[part] for c in columns))))
    tails = np.flatnonzero(~heads)
    for i in range(0, len(tails), _CHUNK):
        part = tails[i : i + _CHUNK]
        rows.append(((salt + i // _CHUNK) % slices, _TAILS, pack(keys[part], *(c[part] for c in columns))))
    cols = list(zip(*rows)) or [()] * 3
    return pa.RecordBatch.from_arrays([pa.array(c, t) for c, t in zip(cols, (pa.int32(), pa.int32(), pa.binary()))], ["slice", "kind", "block"])


def _fingerprint_blocks(window: int, k: int, slices: int) -> Callable:
    """Sorted postings (fingerprint, document, 1 if more documents of the task have it)."""

    def flush(hs, ds):
        h, d = np.concatenate(hs), np.concatenate(ds)
        order = np.lexsort((d, h))
        h, d = h[order], d[order]
        other = np.append(True, (h[1:] != h[:-1]) | (d[1:] != d[:-1]))
        h, d = h[other], d[other]
        first = np.append(True, h[1:] != h[:-1])
        group = np.cumsum(first) - 1
        last = d[np.append(np.flatnonzero(first)[1:], len(h)) - 1]
        several = (last[group] != d[first][group]).astype(np.int64)
        return _blocks(h, first, [d, several], slices, int(h[len(h) // 2] % np.uint64(slices)))

    def run(batches):
        hs, ds, n = [], [], 0
        for batch, texts in _few_texts(batches):
            bounds, a, _ = word_hashes(texts)
            at, h, _ = _window_runs(bounds, a, window, k)
            if len(h):
                hs.append(h)
                ds.append(_longs(batch, "doc_id")[bounds.searchsorted(at, "right") - 1])
                n += len(h)
            if n >= _FLUSH:
                yield flush(hs, ds)
                hs, ds, n = [], [], 0
        if n:
            yield flush(hs, ds)

    return run


_MERGED = f"part string, {_RUN}, doc_id long, h long"


def _merge_fingerprints(batches: Iterator[pa.RecordBatch], slices: int) -> Iterator[pa.RecordBatch]:
    """Slice by slice: the run's blocks, and (doc_id, h) for fingerprints that two documents have."""

    names = ["part", "slice", "least", "n", "block", "doc_id", "h"]

    def suspects(d, h):
        none = [pa.nulls(len(d), t) for t in (pa.int32(), pa.int64(), pa.int64(), pa.binary())]
        return pa.RecordBatch.from_arrays([pa.array(["suspect"] * len(d), pa.string()), *none, pa.array(d), pa.array(h.view(np.int64))], names)

    def postings(rows):
        n = len(rows)
        return pa.RecordBatch.from_arrays([pa.array(["run"] * n, pa.string()), *_run_rows(rows).columns, pa.nulls(n, pa.int64()), pa.nulls(n, pa.int64())], names)

    def merge(parts):
        h, d, several = (np.concatenate(x) for x in zip(*parts))
        order = np.lexsort((d, h))
        h, d, several = h[order], d[order], several[order] > 0
        first = np.append(True, h[1:] != h[:-1])
        group = np.cumsum(first) - 1
        last = d[np.append(np.flatnonzero(first)[1:], len(h)) - 1]
        again = (last != d[first]) | (np.bincount(group, several) > 0)
        return h, d, group, h[first], again

    def finish(key, state):
        h, d, group, _, again = state
        yield postings([(key, h[i : i + _CHUNK], d[i : i + _CHUNK]) for i in range(0, len(h), _CHUNK)])
        own = again[group]
        yield suspects(d[own], h[own])

    now, parts, state = None, [], None
    for batch in batches:
        for key, kind, block in byte_rows(batch, ["slice", "kind", "block"]):
            if key != now:
                if parts or state:
                    yield from finish(now, state or merge(parts))
                now, parts, state = key, [], None
            if kind == _HEADS:
                parts.append(unpack(block, 3))
            elif kind == _PAST:
                if state is None and parts:
                    state = merge(parts)
                if state:
                    h, d = unpack(block, 2)
                    distinct, again = state[3], state[4]
                    at = np.minimum(distinct.searchsorted(h), len(distinct) - 1)
                    same = distinct[at] == h
                    again[at[same]] = True
                    yield suspects(d[same], h[same])
            else:
                h, d, _ = unpack(block, 3)
                yield postings(_by_slice(h, d, slices))
                yield suspects(d, h)
    if parts or state:
        yield from finish(now, state or merge(parts))


def _window_blocks(window: int, k: int, slices: int) -> Callable:
    """Sorted entries (both halves of the window's digest, position, document, 1 if already indexed) of suspect windows."""

    def flush(parts):
        w, c, at, d, old, group, first = _by_digest(parts)
        known = np.maximum.reduceat(old, first)[group]
        least = np.minimum.reduceat(np.where(old == known, d, np.iinfo(np.int64).max), first)[group]
        heads = (old == known) & (d == least)
        keep = heads | (old == 0)
        return _blocks(w[keep], heads[keep], [c[keep].view(np.int64), at[keep], d[keep], old[keep]], slices, int(w[len(w) // 2] % np.uint64(slices)))

    def run(batches):
        parts, n = [], 0
        for batch, texts in _few_texts(batches):
            bounds, a, b = word_hashes(texts)
            at, h, length = _window_runs(bounds, a, window, k)
            row = bounds.searchsorted(at, "right") - 1
            hs = batch.column(batch.schema.get_field_index("hs"))
            # A fingerprint of another row may seem to be one of this row's: the window is then verified for nothing.
            tag = lambda h, row: h + row.astype(np.uint64) * np.uint64(0x9E3779B97F4A7C15)
            asked = np.sort(tag(hs.flatten().to_numpy().view(np.uint64), np.repeat(np.arange(len(hs)), hs.value_lengths().to_numpy())))
            found = tag(h, row)
            hit = asked[np.minimum(asked.searchsorted(found), len(asked) - 1)] == found if len(asked) else np.zeros(len(h), bool)
            at, row, length = at[hit], row[hit], length[hit]
            if len(at):
                row = np.repeat(row, length)
                at = np.repeat(at - np.cumsum(length) + length, length) + np.arange(len(row))
                parts.append((grams(a, window, at), grams(b, window, at), at - bounds[row], _longs(batch, "doc_id")[row], _longs(batch, "old")[row]))
                n += len(at)
            if n >= _FLUSH:
                yield flush(parts)
                parts, n = [], 0
        if n:
            yield flush(parts)

    return run


def _longs(batch: pa.RecordBatch, name: str) -> np.ndarray:
    return batch.column(batch.schema.get_field_index(name)).cast(pa.int64()).to_numpy()


def _by_digest(parts: list[tuple]) -> tuple[np.ndarray, ...]:
    """Entries (both halves, position, document, old) sorted by digest, the group of each, and where groups start."""
    w, c, at, d, old = (np.concatenate(x) for x in zip(*parts))
    c = c.view(np.uint64)
    order = np.argsort(w, kind="stable")
    same = np.flatnonzero(w[order[1:]] == w[order[:-1]])
    if (c[order[same]] != c[order[same + 1]]).any():  # digests that have only one half in common
        order = np.lexsort((c, w))
    w, c, at, d, old = w[order], c[order], at[order], d[order], old[order]
    return w, c, at, d, old, *_groups(w, c)


def _groups(w: np.ndarray, c: np.ndarray) -> tuple[np.ndarray, np.ndarray]:
    """Of sorted digests: the number of the group of each, and where each group starts."""
    first = np.append(True, (w[1:] != w[:-1]) | (c[1:] != c[:-1]))
    return np.cumsum(first) - 1, np.flatnonzero(first)


def _merge_windows(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
    """(doc_id, start): windows whose words also start in an earlier document."""

    def rows(d, at):
        return pa.RecordBatch.from_arrays([pa.array(d), pa.array(at.astype(np.int32))], ["doc_id", "start"])

    def merge(parts):
        _, _, at, d, old, group, first = _by_digest(parts)
        lost = (old == 0) & ((np.maximum.reduceat(old, first)[group] == 1) | (d != np.minimum.reduceat(d, first)[group]))
        return rows(d[lost], at[lost])

    now, parts = None, []
    for batch in batches:
        for key, kind, block in byte_rows(batch, ["slice", "kind", "block"]):
            if key != now and parts:
                yield merge(parts)
                parts = []
            now = key
            if kind == _HEADS:
                parts.append(unpack(block, 5))
            else:
                _, _, at, d, _ = unpack(block, 5)
                yield rows(d, at)
    if parts:
        yield merge(parts)


def _to_slices(blocks: DataFrame) -> DataFrame:
    return blocks.repartition("slice").sortWithinPartitions("slice", "kind")


def _named(docs: DataFrame, id_col: str, text_col: str) -> DataFrame:
    """Ids and texts under names of their own, so that all joins below plan the same shuffle of the texts and share it."""
    return docs.select(F.col(f"`{id_col}`").alias("__id"), F.col(f"`{text_col}`").alias("__body")).filter("__id IS NOT NULL")


def _lost_windows(view: DataFrame, own: DataFrame, past: DataFrame | None, index: FingerprintIndex, window: int, k: int, most_runs: int) -> DataFrame:
    """(doc_id, starts) of the windows that a batch loses; the batch becomes a run of the index.

    ``view`` (doc_id, text) is scanned once; ``own`` and ``past`` (__id, __body) are the texts of the batch
    and of what the index holds, joined with the documents that have suspects.
    """
    if index.runs() and past is None:
        raise ValueError("the index holds documents already: give their texts as history, or repeats of them would stay")
    blocks = view.mapInArrow(_fingerprint_blocks(window, k, index.slices), _BLOCKS)
    if (known := index.read()) is not None:
        blocks = blocks.unionByName(known.select("slice", F.lit(_PAST).alias("kind"), "block"))
    run, slices = scratch_path(index.spark, "merged-fingerprints"), index.slices
    _to_slices(blocks).mapInArrow(lambda batches: _merge_fingerprints(batches, slices), _MERGED).write.partitionBy("part").parquet(run)
    index.commit(f"{run}/part=run")
    if len(index.runs()) > most_runs:
        index.compact()
    found = index.spark.read.schema(_MERGED).parquet(run).filter("part = 'suspect'").select("doc_id", "h")
    spread = min(2 * int(index.spark.conf.get("spark.sql.shuffle.partitions")), 1 + found.count() // _SLICE_SUSPECTS)
    suspects = found.groupBy(F.col("doc_id").alias("__id")).agg(F.collect_set("h").alias("hs"))
    named = [F.col("__id").alias("doc_id"), F.col("__body").alias("text"), "hs"]
    texts = own.join(suspects, "__id").select(*named, F.lit(0).alias("old"))
    if past is not None:
        texts = texts.unionByName(past.join(suspects, "__id").select(*named, F.lit(1).alias("old")))
    lost = _to_slices(texts.mapInArrow(_window_blocks(window, k, spread), _BLOCKS)).mapInArrow(_merge_windows, "doc_id long, start int")
    return lost.groupBy(F.col("doc_id").alias("__id")).agg(F.collect_list("start").alias("starts"))


_KEPT = "doc_id long, n_words long, n_removed long, kept_sha256 string, kept string"


def _without(rows: DataFrame, window: int, keep_text: bool) -> DataFrame:
    """Rows of ``_KEPT`` from (__id, __body, starts); without ``keep_text`` the remaining words stay null."""

    def finish(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in batches:
            out, starts = [], batch.column(batch.schema.get_field_index("starts"))
            for i, (doc_id, raw) in enumerate(byte_rows(batch, ["__id", "__body"])):
                words = (raw or b"").split()
                n, kept = len(words), words
                if starts[i].is_valid:
                    at = starts[i].values.to_numpy()
                    at = at[at + window <= n]  # rows that repeat an id may be shorter
                    depth = np.cumsum(np.bincount(at, minlength=n + 1) - np.bincount(at + window, minlength=n + 1))
                    kept = [words[j] for j in np.flatnonzero(depth[:n] == 0).tolist()]
                text = b" ".join(kept)
                out.append((doc_id, n, n - len(kept), hashlib.sha256(text).hexdigest(), text.decode() if keep_text else None))
            cols = list(zip(*out)) or [()] * 5
            yield pa.RecordBatch.from_arrays([pa.array(c, t) for c, t in zip(cols, (pa.int64(), pa.int64(), pa.int64(), pa.string(), pa.string()))], ["doc_id", "n_words", "n_removed", "kept_sha256", "kept"])

    return rows.select("__id", "__body", "starts").mapInArrow(finish, _KEPT)


def _nameless(docs: DataFrame, id_col: str, text_col: str) -> DataFrame:
    view = documents_view(docs, id_col, text_col).filter("doc_id IS NULL")
    return view.select(F.col("doc_id").alias("__id"), F.col("text").alias("__body"), F.lit(None).cast("array<int>").alias("starts"))


def remove_repeats(
    docs: DataFrame, index: FingerprintIndex, history: DataFrame | None = None, id_col: str = "doc_id", text_col: str = "text",
    *, window: int = 13, k: int = 5, most_runs: int = 8,
) -> DataFrame:
    """One row per input row: doc_id, n_words, n_removed, kept_sha256, kept (the words that remain).

    A word goes if a window that covers it has the word sequence of a window of a document with a
    smaller doc_id, or of any document that ``index`` already holds; ``history`` then gives those
    documents' ids and texts, and an index that holds any without it is an error.  The batch becomes a
    run of the index, which is compacted beyond ``most_runs`` runs.  Null, empty and blank texts have no
    words; texts shorter than a window lose none.  Rows with a null doc_id keep everything and are not
    indexed; rows that repeat a doc_id are one document and never remove each other's words.
    """
    own = _named(docs, id_col, text_col)
    past = None if history is None else _named(history, id_col, text_col)
    lost = _lost_windows(documents_view(docs, id_col, text_col).filter("doc_id IS NOT NULL"), own, past, index, window, k, most_runs)
    return _without(own.join(lost, "__id", "left").unionByName(_nameless(docs, id_col, text_col)), window, True)


def remove_repeats_in_batches(
    docs: DataFrame, index: FingerprintIndex, cuts: tuple[float, ...] = (0.8, 0.9), id_col: str = "doc_id", text_col: str = "text",
    *, window: int = 13, k: int = 5, most_runs: int = 2, keep_text: bool = False,
) -> DataFrame:
    """``remove_repeats`` of a whole corpus by an index that grows: batches of ascending doc_id, cut at quantiles of it.

    By default the first batch is a corpus's initial load, and two increments follow.  The result is that
    of one batch, as earlier batches have smaller ids.  The texts are shuffled once,
    into a table bucketed by id that every batch and its history read; the index must be empty.  All rows
    are written before this returns.  Without ``keep_text`` column kept is null.
    """
    spark = docs.sparkSession
    if index.runs():
        raise ValueError("the index must be empty: its documents may have larger ids than these")
    table, buckets = f"flowrings_texts_{uuid.uuid4().hex}", int(spark.conf.get("spark.sql.shuffle.partitions"))
    own = _named(docs, id_col, text_col)
    bounds = [int(x) for x in own.approxQuantile("__id", list(cuts), 0.01)]
    own.repartition(buckets, "__id").write.option("path", scratch_path(spark, "texts")).option("compression", "zstd").bucketBy(buckets, "__id").saveAsTable(table)
    texts, parts = spark.table(table), [_without(_nameless(docs, id_col, text_col), window, keep_text)]
    view = documents_view(docs, id_col, text_col).filter("doc_id IS NOT NULL")
    try:
        for low, high in zip([None, *bounds], [*bounds, None]):
            within = lambda c, low=low, high=high: (F.lit(True) if low is None else F.col(c) > low) & (F.lit(True) if high is None else F.col(c) <= high)
            past = None if low is None else texts.filter(F.col("__id") <= low)
            batch = texts.filter(within("__id"))
            lost = _lost_windows(view.filter(within("doc_id")), batch, past, index, window, k, most_runs)
            parts.append(materialize(_without(batch.join(lost, "__id", "left"), window, keep_text), "without-repeats"))
            del lost, batch, past
            release_shuffles(spark)
    finally:
        spark.sql(f"DROP TABLE {table}")
    out = parts[0]
    for x in parts[1:]:
        out = out.unionByName(x)
    return out


def op4_substring_dedup(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Three batches: the second and third meet the runs of those before, and the last compacts them."""
    index = FingerprintIndex(spark, scratch_path(spark, "fingerprint-index"))
    return remove_repeats_in_batches(spark.read.parquet(f"{sf_dir}/documents.parquet"), index).drop("kept")


ORACLE = r"""
WITH d AS (SELECT doc_id, regexp_extract_all(coalesce(text, ''), '[^\x20\x09-\x0D]+') AS w FROM documents),
s AS (SELECT doc_id, i, array_to_string(w[i : i + 12], ' ') AS win FROM d, unnest(generate_series(1, len(w) - 12)) AS t(i) WHERE len(w) >= 13),
f AS (SELECT win, min(doc_id) AS first_doc FROM s GROUP BY 1),
c AS (SELECT DISTINCT doc_id, unnest(generate_series(i, i + 12)) AS p FROM s JOIN f USING (win) WHERE first_doc < doc_id),
g AS (SELECT doc_id, list(p) AS gone, count(*) AS n FROM c GROUP BY 1),
k AS (SELECT d.doc_id, string_agg(w[t.p], ' ' ORDER BY t.p) AS kept FROM d CROSS JOIN unnest(generate_series(1, len(w))) AS t(p)
      LEFT JOIN c ON c.doc_id = d.doc_id AND c.p = t.p WHERE c.p IS NULL GROUP BY 1)
SELECT d.doc_id, CAST(len(w) AS BIGINT) AS n_words, coalesce(g.n, 0) AS n_removed, sha256(coalesce(kept, '')) AS kept_sha256
FROM d LEFT JOIN g USING (doc_id) LEFT JOIN k USING (doc_id)
"""
