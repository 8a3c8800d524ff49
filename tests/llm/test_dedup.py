"""Exact, near, line and substring deduplication against brute force."""

import hashlib
import random
import re
from collections import defaultdict

import numpy as np
import pyarrow as pa
import pytest
import xxhash

from flowrings.llm import exact_dedup, line_dedup, simhash, substring_dedup
from flowrings.llm.rolling import pack, unpack
from flowrings.scratch import scratch_path

sha = lambda s: hashlib.sha256(s.encode()).hexdigest()


def test_exact(documents, prose):
    got = {r.doc_id: r for r in exact_dedup.deduplicate_once(documents(prose)).collect()}
    groups = defaultdict(list)
    for i, t in enumerate(prose):
        groups[t or ""].append(i)
    for i, t in enumerate(prose):
        g = groups[t or ""]
        assert (got[i].keep_id, got[i].group_size, got[i].kept, got[i].text_sha256) == (max(g), len(g), i == max(g), sha(t or ""))


def test_exact_index_grows_and_remembers(spark, documents):
    index = exact_dedup.DigestIndex(spark, "digests_test", 4)
    index.drop()
    try:
        exact_dedup.deduplicate(documents(["a", "b", None]), index).collect()
        got = {r.doc_id: (r.keep_id, r.kept) for r in exact_dedup.deduplicate(documents(["b", "c", "c", ""], [10, 11, 12, 13]), index).collect()}
        assert got == {10: (1, False), 11: (12, False), 12: (12, True), 13: (2, False)}
        assert index.read().count() == 4
        exact_dedup.deduplicate(documents(["b", "c", "c", ""], [10, 11, 12, 13]), index).collect()
        assert index.read().count() == 4
        assert exact_dedup.deduplicate(documents(["b"]).limit(0), index).count() == 0
    finally:
        index.drop()


@pytest.mark.parametrize("batches", [1, 3, 7])
def test_exact_in_batches_equals_one(spark, documents, prose, batches):
    """Batches of descending ids through a growing index: the same rows, null ids and repeated ids included."""
    texts, ids = [*prose, "same", "same", "same", "only null", None], [*range(len(prose)), 7, 7, None, None, None]
    show = lambda df: sorted(map(str, df.select("doc_id", "keep_id", "group_size", "kept", "text_sha256").collect()))
    want = show(exact_dedup.deduplicate_once(documents(texts, ids), batches=1))
    index = exact_dedup.DigestIndex(spark, f"digests_batches_{batches}", 4)
    index.drop()
    try:
        assert show(exact_dedup.deduplicate_in_batches(documents(texts, ids), index, batches)) == want
        assert index.read().count() == len({t or "" for t in texts})
    finally:
        index.drop()


def brute_fingerprint(text):
    words = re.findall(r"[^\x20\x09-\x0D]+", "".join(c.lower() if c.isascii() else c for c in text))
    if not words:
        return 0
    shingles = [" ".join(words[i : i + 3]) for i in range(max(1, len(words) - 2))]
    hs = [xxhash.xxh64_intdigest(s.encode(), 42) for s in shingles]
    return sum(1 << b for b in range(64) if sum(h >> b & 1 for h in hs) * 2 > len(hs))


def brute_components(fps, most=3):
    root = list(range(len(fps)))

    def find(x):
        while root[x] != x:
            x = root[x]
        return x

    for i in range(len(fps)):
        for j in range(i):
            if (fps[i] ^ fps[j]).bit_count() <= most:
                a, b = find(i), find(j)
                root[max(a, b)] = min(a, b)
    return [find(i) for i in range(len(fps))]


def test_simhash(documents, prose):
    got = {r.doc_id: (r.fingerprint, r.component_id) for r in simhash.near_components(documents(prose)).collect()}
    fps = [brute_fingerprint(t or "") for t in prose]
    assert got == {i: (f"{f:016x}", c) for i, (f, c) in enumerate(zip(fps, brute_components(fps)))}


@pytest.mark.parametrize("longest", [3, 256])
def test_long_posting_lists_lose_no_link(spark, longest):
    rng = random.Random(5)
    fps = list({c ^ sum(1 << b for b in rng.sample(range(64), rng.randrange(6))) for c in [rng.getrandbits(64) for _ in range(4)] for _ in range(60)})
    frame = spark.createDataFrame([(simhash._signed(f),) for f in fps], "fp long")
    links = [(r.a & (1 << 64) - 1, r.b & (1 << 64) - 1) for r in simhash.near_links(frame, longest=longest).collect()]
    assert all((a ^ b).bit_count() <= 3 for a, b in links)
    place = {f: i for i, f in enumerate(fps)}
    root = list(range(len(fps)))

    def find(x):
        while root[x] != x:
            x = root[x]
        return x

    for a, b in links:
        x, y = find(place[a]), find(place[b])
        root[max(x, y)] = min(x, y)
    assert [find(i) for i in range(len(fps))] == brute_components(fps)


def test_tally_counts_shared_positional_bytes():
    """Pairs from the posting lists are exactly those that share enough bytes, in small and large partitions."""
    rng = np.random.default_rng(3)
    for n in (2, 3, 40):
        for common in (0, 4, 7):
            table = rng.integers(0, 3, (n, 8), dtype=np.uint8)
            table[:, :common] = 7
            fps = np.unique(table.reshape(-1).view(np.uint64))
            own = fps.view(np.uint8).reshape(-1, 8)
            want = {(i, j) for i in range(len(fps)) for j in range(i + 1, len(fps)) if (own[i] == own[j]).sum() >= 5}
            if len(fps) > 1:
                assert set(zip(*(x.tolist() for x in simhash.tallied_pairs(fps, 5)))) == want


def test_blocks_avoid_any_three_positions():
    for bad in [(a, b, c) for a in range(8) for b in range(a) for c in range(b)]:
        assert sum(not set(bad) & set(q) for q in simhash.blocks()) >= 1


def brute_lines(texts, least=20, docs=3):
    key = lambda x: "".join(c.lower() if c.isascii() else c for c in x.strip(" \t\n\r\x0b\x0c"))
    where = defaultdict(set)
    for i, t in enumerate(texts):
        for x in (t or "").split("\n"):
            where[key(x)].add(i)
    gone = lambda i, x: len(key(x)) >= least and len(where[key(x)]) >= docs and i != max(where[key(x)])
    out = {}
    for i, t in enumerate(texts):
        lines = (t or "").split("\n")
        kept = [x for x in lines if not gone(i, x)]
        out[i] = (len(lines), len(lines) - len(kept), sha("\n".join(kept)))
    return out


@pytest.mark.parametrize("most, least, bits", [(28, 20, 8), (28, 16, 0), (10, 20, 8), (10, 20, 0)])
def test_lines(documents, prose, most, least, bits, monkeypatch):
    """With a filter that is sent and with filters by slice, also far too small ones."""
    monkeypatch.setattr(line_dedup, "_LEAST_LOG2", least)
    monkeypatch.setattr(line_dedup, "_BITS", bits)
    monkeypatch.setattr(line_dedup, "_SLICE_LINES", 50)
    docs = documents([*prose, prose[9]], [*range(len(prose)), None])
    got = {r.doc_id: (r.n_lines, r.n_dropped, r.kept_sha256) for r in line_dedup.drop_repeated_lines(docs, most_log2_bits=most if bits else 28 if most == 28 else -1).collect()}
    want = brute_lines([prose[9], *prose])  # the row without an id counts, and never keeps a line for itself
    assert {i: x for i, x in got.items() if i is not None} == {i - 1: x for i, x in want.items() if i}
    assert any(n for _, n, _ in got.values()) and got[None][1] == 0


def brute_windows(texts, size=13, past=()):
    words = [re.findall(r"[^\x20\x09-\x0D]+", t or "") for t in texts]
    first = {}
    for t in past:
        w = re.findall(r"[^\x20\x09-\x0D]+", t or "")
        for j in range(len(w) - size + 1):
            first[tuple(w[j : j + size])] = -1
    for i, w in enumerate(words):
        for j in range(len(w) - size + 1):
            first.setdefault(tuple(w[j : j + size]), i)
    out = {}
    for i, w in enumerate(words):
        gone = {p for j in range(len(w) - size + 1) if first[tuple(w[j : j + size])] < i for p in range(j, j + size)}
        out[i] = (len(w), len(gone), sha(" ".join(x for p, x in enumerate(w) if p not in gone)))
    return out


def rows(df):
    return {r.doc_id: (r.n_words, r.n_removed, r.kept_sha256) for r in df.collect()}


def test_substrings(spark, documents, prose):
    index = substring_dedup.FingerprintIndex(spark, scratch_path(spark, "t-index"), 8)
    got = rows(substring_dedup.remove_repeats(documents(prose), index))
    assert got == brute_windows(prose) and any(n for _, n, _ in got.values())


def test_substrings_in_batches(spark, documents, prose):
    index = substring_dedup.FingerprintIndex(spark, scratch_path(spark, "t-index"), 8)
    cut, n = len(prose) // 2, len(prose)
    first, second = documents(prose[:cut], range(1000, 1000 + cut)), documents(prose[cut:])
    assert list(rows(substring_dedup.remove_repeats(first, index)).values()) is not None
    assert len(index.runs()) == 1
    got = rows(substring_dedup.remove_repeats(second, index, history=first, most_runs=1))
    assert got == brute_windows(prose[cut:], past=prose[:cut])
    assert len(index.runs()) == 1 and substring_dedup.FingerprintIndex(spark, index.path).slices == 8
    again = rows(substring_dedup.remove_repeats(documents(prose[:5], range(n, n + 5)), index, history=first.unionByName(second)))
    assert all(kept[0] < 13 or kept[1] == kept[0] for kept in again.values())


@pytest.mark.parametrize("cuts", [(0.8, 0.9), (0.1, 0.2, 0.5, 0.9)])
def test_substrings_of_a_corpus_in_batches(spark, documents, prose, cuts, monkeypatch):
    """An index that grows and is compacted, also into more slices and small blocks, gives what one batch gives."""
    monkeypatch.setattr(substring_dedup, "_SLICE_POSTINGS", 100)
    monkeypatch.setattr(substring_dedup, "_CHUNK", 7)
    texts, ids = [*prose, prose[9], prose[9]], [*range(len(prose)), None, 3]
    index = substring_dedup.FingerprintIndex(spark, scratch_path(spark, "t-index"), 2)
    got = substring_dedup.remove_repeats_in_batches(documents(texts, ids), index, cuts)
    one = substring_dedup.FingerprintIndex(spark, scratch_path(spark, "t-index"), 2)
    want = substring_dedup.remove_repeats(documents(texts, ids), one)
    columns = ["doc_id", "n_words", "n_removed", "kept_sha256"]
    assert sorted(map(str, got.select(*columns).collect())) == sorted(map(str, want.select(*columns).collect()))
    assert len(index.runs()) <= 2 and index.slices > 2
    postings = lambda i: sorted((int(h), int(d)) for r in i.read().collect() for h, d in zip(*unpack(r.block, 2)))
    assert postings(index) == postings(one) and all(r.n == len(unpack(r.block, 2)[0]) for r in index.read().collect())
    with pytest.raises(ValueError, match="empty"):
        substring_dedup.remove_repeats_in_batches(documents(texts, ids), index)


def test_filled_index_needs_its_texts(spark, documents):
    long = " ".join(f"w{i}" for i in range(30))
    index = substring_dedup.FingerprintIndex(spark, scratch_path(spark, "t-index"), 3)
    substring_dedup.remove_repeats(documents([long], [1]), index).collect()
    with pytest.raises(ValueError, match="history"):
        substring_dedup.remove_repeats(documents([long], [2]), index)
    assert rows(substring_dedup.remove_repeats(documents([long], [2]), index, history=documents([long], [1])))[2][1] == 30


def test_long_texts_and_repeated_rows(spark, documents):
    """A text of 200,000 words, equal rows with one id, equal rows with two."""
    huge = " ".join(f"{i:x}" for i in range(200_000))
    docs = documents([huge, huge, huge + " tail", "short", "short"], [1, 1, 2, 3, 4])
    index = substring_dedup.FingerprintIndex(spark, scratch_path(spark, "t-index"), 3)
    got = sorted((r.doc_id, r.n_words, r.n_removed) for r in substring_dedup.remove_repeats_in_batches(docs, index).collect())
    assert got == [(1, 200_000, 0), (1, 200_000, 0), (2, 200_001, 200_000), (3, 1, 0), (4, 1, 0)]
    lines = line_dedup.drop_repeated_lines(documents(["a" * 300_000 + "\nx"] * 3 + [None], [1, 2, 3, 3])).collect()
    assert sorted((r.doc_id, r.n_lines, r.n_dropped) for r in lines) == [(1, 2, 1), (2, 2, 1), (3, 1, 0), (3, 2, 0)]


def test_words_are_hashed_at_once(prose, monkeypatch):
    """The words that bytes.split finds, equal hashes for equal words only, and no call for each word of usual length."""
    calls, digest = [], xxhash.xxh3_128_digest
    monkeypatch.setattr(substring_dedup.xxhash, "xxh3_128_digest", lambda word: calls.append(word) or digest(word))
    odd = ["", " a\tb  c ", "", "\xa0z\x1cq\x85 é", "cd \x0b\x0c\r\n", "abcdefgh abcdefghi abcdefghabcdefgh", *(n * "w" for n in (7, 8, 9, 16, 17, 63, 64)), 65 * "w" + " " + 70 * "é"]
    texts = pa.array([(t or "").encode() for t in odd + prose])
    for part in (texts, texts.slice(2), texts.slice(3, 4), texts.slice(0, 1), texts.slice(0, 0)):
        words = [t.split() for t in part.to_pylist()]
        bounds, a, b = substring_dedup.word_hashes(part)
        assert np.diff(bounds).tolist() == list(map(len, words))
        flat = [w for ws in words for w in ws]
        assert len(a) == len(b) == len(flat)
        for half in (a, b):
            known = dict(zip(flat, half.tolist()))
            assert [known[w] for w in flat] == half.tolist() and len(set(known.values())) == len(known)
    assert set(calls) == {65 * b"w", 70 * "é".encode()}
    batch = pa.RecordBatch.from_arrays([pa.array(range(len(prose))), pa.array(prose)], ["doc_id", "text"])
    calls.clear()
    assert sum(b.num_rows for b in substring_dedup._fingerprint_blocks(13, 5, 4)([batch])) and not calls


def test_texts_come_in_batches_of_bytes(prose):
    ids = [None if i % 5 == 0 else i for i in range(len(prose))]
    batch = pa.RecordBatch.from_arrays([pa.array(ids), pa.array(prose)], ["doc_id", "text"])
    for most in (1, 300, 1 << 20):
        parts = list(substring_dedup._few_texts([batch.slice(0, 0), batch.slice(3)], most))
        got = [(i, t) for b, texts in parts for i, t in zip(b.column(0).to_pylist(), texts.to_pylist())]
        assert got == [(i, (t or "").encode()) for i, t in list(zip(ids, prose))[3:] if i is not None]
        assert all(len(texts) == 1 or sum(map(len, texts.to_pylist())) <= most for _, texts in parts)


def test_flushes_do_not_matter(spark, documents, prose, monkeypatch):
    monkeypatch.setattr(substring_dedup, "_FLUSH", 50)
    monkeypatch.setattr(substring_dedup, "_CHUNK", 7)
    index = substring_dedup.FingerprintIndex(spark, scratch_path(spark, "t-index"), 3)
    assert rows(substring_dedup.remove_repeats(documents(prose), index)) == brute_windows(prose)


def test_empty_tables(spark, documents):
    none = documents(["x"]).limit(0)
    index = substring_dedup.FingerprintIndex(spark, scratch_path(spark, "t-index"), 3)
    whole = substring_dedup.remove_repeats_in_batches(none, substring_dedup.FingerprintIndex(spark, scratch_path(spark, "t-index"), 3))
    for df in (exact_dedup.deduplicate_once(none), simhash.near_components(none), line_dedup.drop_repeated_lines(none), substring_dedup.remove_repeats(none, index), whole):
        assert df.count() == 0


def test_null_ids_keep_everything(spark, documents):
    long = " ".join(f"w{i}" for i in range(30))
    docs = documents([long, long, long], [None, 1, 2])
    index = substring_dedup.FingerprintIndex(spark, scratch_path(spark, "t-index"), 3)
    assert rows(substring_dedup.remove_repeats(docs, index))[None][1] == 0
    assert {r.doc_id: r.kept for r in exact_dedup.deduplicate_once(docs).collect()} == {None: False, 1: False, 2: True}
    assert {r.doc_id: r.component_id for r in simhash.near_components(docs).collect()} == {None: 1, 1: 1, 2: 1}
    assert {r.doc_id: r.n_dropped for r in line_dedup.drop_repeated_lines(docs).collect()} == {None: 0, 1: 1, 2: 0}


def test_pack_round_trip():
    rng = np.random.default_rng(1)
    h = np.sort(rng.integers(0, 2**64, 500, dtype=np.uint64))
    d = rng.integers(-5, 2**40, 500)
    got = unpack(pack(h, d), 2)
    assert (got[0] == h).all() and (got[1] == d).all()
