"""BPE encoding and decoding of whole texts by a depth-first walk over the trie of distinct words.

The encoding of a word's prefix is known from one state: its last token.  A token that ends at a trie
node is the last one there if it may follow the last token of the node where it starts, so states are
propagated from parent to child and the words below a node share all states above it.  The sorted
list of distinct words is the trie in depth-first order: the path common to two neighbours is kept.
The final byte of a word is another symbol (it carries the end-of-word mark), a leaf of its own.
"""

from __future__ import annotations

import hashlib
import json
from collections.abc import Iterator
from functools import lru_cache

import numpy as np
import pyarrow as pa
import regex
from pyspark.sql import DataFrame, SparkSession

from flowrings.llm.arrow import byte_rows, documents_view, give_back_memory, small_batches

_END = "</w>"
_LATIN = regex.compile(r"[^\x00-ɏ]")
# Fixed value: the word pattern of the vocabulary; white space as Unicode lists it below U+0250.
_ODD = regex.compile(r"[\x1c-\x1f]")
_WORD = regex.compile(r"'s|'t|'re|'ve|'m|'ll|'d|\p{L}+|\p{N}|[^\t-\r \x85\xa0\p{L}\p{N}]+")


def _byte_alphabet() -> dict[str, int]:
    """Printable bytes stand for themselves, the others for the characters from U+0100 on."""
    plain = [*range(33, 127), *range(161, 173), *range(174, 256)]
    rest = [b for b in range(256) if b not in set(plain)]
    return {chr(b): b for b in plain} | {chr(256 + i): b for i, b in enumerate(rest)}


class WordTrie:
    """Encoder and decoder for one vocabulary file.  The memory for known words is bounded."""

    def __init__(self, path: str, max_chunks: int = 300_000):
        from tokenizers import Tokenizer

        with open(path, encoding="utf-8") as f:
            spec = json.load(f)
        self._lib = Tokenizer.from_file(path)
        to_byte, model = _byte_alphabet(), spec["model"]
        vocab = model["vocab"]
        self.names = {i: s for s, i in vocab.items()}
        self.specials = {x["content"]: x["id"] for x in spec["added_tokens"]}
        self.names |= {i: s for s, i in self.specials.items()}
        self._split_at = regex.compile("(" + "|".join(map(regex.escape, self.specials)) + ")") if self.specials else None
        raw = lambda s: bytes(to_byte[c] for c in s)
        self.inner = {raw(s): i for s, i in vocab.items() if not s.endswith(_END)}
        self.final = {raw(s[: -len(_END)]): i for s, i in vocab.items() if s.endswith(_END)}
        self.size = {i: len(b) for m in (self.inner, self.final) for b, i in m.items()}
        self.longest = max(self.size.values())
        self.merged, self.parts = {}, {}
        for a, b in (x if isinstance(x, list) else x.split(" ") for x in model["merges"]):
            pair, made = (vocab[a], vocab[b]), vocab[a + b]
            self.merged.setdefault(pair, made)
            self.parts.setdefault(made, pair)
        self._follows: dict[tuple[int, int], bool] = {}
        self._whole: dict[int, bool] = {}
        self.max_chunks = max_chunks
        self.ids, self.text, self.old_ids, self.old_text = {}, {}, {}, {}

    def whole(self, token: int) -> bool:
        """Whether the token's own bytes encode to the token."""
        if (ok := self._whole.get(token)) is None:
            pair = self.parts.get(token)
            ok = self._whole[token] = pair is None or self.merged[pair] == token and self.whole(pair[0]) and self.whole(pair[1]) and self._join(*pair, token)
        return ok

    def follows(self, a: int, b: int) -> bool:
        """Whether tokens a, b stay apart when their bytes are encoded together."""
        if (ok := self._follows.get((a, b))) is None:
            if len(self._follows) > 2_000_000:
                self._follows.clear()
            ok = self._follows[a, b] = self._join(a, b, 1 << 60)
        return ok

    def _join(self, a: int, b: int, limit: int) -> bool:
        """No merge ranked before ``limit`` crosses the border while either side is still being built."""
        while True:
            if self.merged.get((a, b), limit) < limit:
                return False
            if a > b:  # a is the later merge: before it, its right part was at the border
                limit = min(limit, a)
                if a not in self.parts:
                    return True
                a = self.parts[a][1]
            else:
                limit = min(limit, b + 1)
                if b not in self.parts:
                    return True
                b = self.parts[b][0]

    def _last(self, word: bytes, d: int, states: list[int], table: dict[bytes, int]) -> int:
        """The last token of word[:d]; states[i] is that of word[:i]."""
        for start in range(max(0, d - self.longest), d):
            token = table.get(word[start:d])
            if token is not None and self.whole(token) and (start == 0 or self.follows(states[start], token)):
                return token
        raise ValueError(f"no token ends {word[:d]!r}")

    def walk(self, words: set[str]) -> dict[str, list[int]]:
        """Encode distinct words in one walk over their trie."""
        found, states, before = {}, [0], b""
        for raw, word in sorted((w.encode(), w) for w in words):
            n, common = len(raw), 0
            most = min(n, len(before), len(states) - 1)
            while common < most and raw[common] == before[common]:
                common += 1
            del states[common + 1 :]
            for d in range(len(states), n):
                states.append(self._last(raw, d, states, self.inner))
            tokens, at = [self._last(raw, n, states, self.final)], n
            while (at := at - self.size[tokens[-1]]) > 0:
                tokens.append(states[at])
            found[word] = tokens[::-1]
            before = raw
        return found

    def words(self, text: str) -> list[str]:
        """The words of a text without special tokens, in the vocabulary's normal form."""
        low = text.lower()
        if not (_LATIN.search(text) or _LATIN.search(low)):
            return _WORD.findall(low)
        text = self._lib.normalizer.normalize_str(text)
        to_byte = _byte_alphabet()
        return [bytes(to_byte[c] for c in w).decode() for w, _ in self._lib.pre_tokenizer.pre_tokenize_str(text)]

    def chunks(self, text: str) -> list[str]:
        """Pieces that encode independently: runs without white space of plain texts, else words.

        A special token is a piece with a space before its name, which no other piece contains.
        """
        if "<|" in text and self._split_at is not None and self._split_at.search(text):
            parts = self._split_at.split(text)
            return [c for p in parts for c in ([" " + p] if p in self.specials else self.chunks(p))]
        low = text.lower()
        if _ODD.search(text) or not text.isascii() and (_LATIN.search(text) or _LATIN.search(low)):
            return self.words(text)
        return low.split()

    def encode_batch(self, texts: list[str]) -> Iterator[tuple[str, str]]:
        """For each text its ids and its decoded text, both as strings."""
        split = [self.chunks(t) for t in texts]
        new = {c for chunks in split for c in chunks if c not in self.ids}
        again = {c for c in new if c in self.old_ids}
        if len(self.ids) + len(new) > self.max_chunks:  # two generations: what is still in use survives
            again = set().union(*split) & (self.ids.keys() | self.old_ids.keys())
            new |= again
            self.old_ids, self.old_text = self.ids | {c: self.old_ids[c] for c in again if c in self.old_ids}, self.text | {c: self.old_text[c] for c in again if c in self.old_text}
            self.ids, self.text = {}, {}
        for c in again:
            self.ids[c], self.text[c] = self.old_ids[c], self.old_text[c]
        own = {c: [c] if c[0] == " " or _LATIN.search(c) else _WORD.findall(c) for c in new - again}
        known = self.walk({w for ws in own.values() for w in ws if w[0] != " "}) | {" " + s: [i] for s, i in self.specials.items()}
        for c, ws in own.items():
            tokens = [t for w in ws for t in known[w]]
            self.ids[c], self.text[c] = " ".join(map(str, tokens)), " ".join([self.names[t] for t in tokens])
        for chunks in split:
            yield " ".join(map(self.ids.__getitem__, chunks)), " ".join(map(self.text.__getitem__, chunks))

    def forget(self) -> None:
        """Drop the known chunks and pairs; the vocabulary stays."""
        self.ids, self.text, self.old_ids, self.old_text = {}, {}, {}, {}
        self._follows = {}

    def encode(self, text: str) -> list[int]:
        return [int(x) for x in next(iter(self.encode_batch([text])))[0].split()]

    def decode(self, ids: list[int]) -> str:
        """Token names joined by spaces: the vocabulary file names no decoder."""
        return " ".join(self.names[i] for i in ids)


@lru_cache(maxsize=2)
def trie(path: str) -> WordTrie:
    """One encoder for each Python worker."""
    return WordTrie(path)


def encode_documents(docs: DataFrame, vocabulary: str, id_col: str = "doc_id", text_col: str = "text", keep_ids: bool = True) -> DataFrame:
    """One row per input row: doc_id, n_tokens, ids_sha256, decoded_sha256 and, if ``keep_ids``, ids.

    Null and empty texts have no tokens.  ``vocabulary`` is the path of the file on every executor.
    """
    names = ["doc_id", "n_tokens", "ids_sha256", "decoded_sha256", "ids"][: 4 + keep_ids]
    kinds = [pa.int64(), pa.int64(), pa.string(), pa.string()]

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        coder, sha = trie(vocabulary), lambda s: hashlib.sha256(s.encode()).hexdigest()
        try:
            for batch in small_batches(batches):
                ids_in, texts = [], []
                for doc_id, raw in byte_rows(batch, ["doc_id", "text"]):
                    ids_in.append(doc_id)
                    texts.append((raw or b"").decode())
                out, numbers = [], []
                for ids, text in coder.encode_batch(texts):
                    out.append((ids.count(" ") + 1 if ids else 0, sha(ids), sha(text)))
                    if keep_ids:
                        numbers.append(np.fromstring(ids, np.int32, sep=" ") if ids else np.empty(0, np.int32))
                n, ids_sha, text_sha = zip(*out) if out else ((), (), ())
                arrays = [pa.array(c, t) for c, t in zip((ids_in, n, ids_sha, text_sha), kinds)]
                if keep_ids:
                    ends = np.concatenate([[0], np.cumsum(n, dtype=np.int64)]).astype(np.int32)
                    arrays.append(pa.ListArray.from_arrays(pa.array(ends), pa.array(np.concatenate(numbers) if numbers else np.empty(0, np.int32))))
                yield pa.RecordBatch.from_arrays(arrays, names)
        finally:
            coder.forget()
            give_back_memory()

    schema = "doc_id long, n_tokens long, ids_sha256 string, decoded_sha256 string" + ", ids array<int>" * keep_ids
    return documents_view(docs, id_col, text_col).mapInArrow(run, schema)


def default_vocabulary() -> str:
    import public_tokenizers

    return public_tokenizers.path("word_bpe_49k.json")


def op8_bpe(spark: SparkSession, sf_dir: str) -> DataFrame:
    return encode_documents(spark.read.parquet(f"{sf_dir}/documents.parquet"), default_vocabulary(), keep_ids=False)
