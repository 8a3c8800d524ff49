"""SimHash near-duplicates by an inverted index over byte positions, with count filtering.

Two 64-bit fingerprints within 3 bits differ in at most 3 of their 8 bytes, so they share at least 5
positional bytes: the guaranteed minimum.  A list over one position alone would hold 1/256 of all
fingerprints, so the index has two levels.  A partition of it holds the fingerprints that agree in 4 given
positions, which count 4; the 14 blocks of the Steiner system S(3,4,8) are enough partitions, since the
complement of one of them avoids any 3 differing positions.  Inside a partition each further position has
a posting list for each byte, the counts of a pair are added up over these lists, and only pairs that
reach the minimum exist at all; those are verified bit by bit.

A partition that is too large (many near-copies) is refined in the same way over the nibbles, then the
2-bit pieces, then the bits that are left, so no task ever compares more than ``longest`` fingerprints
and no pair is lost.  A partition yields a spanning forest of its links instead of all of them.
"""

from __future__ import annotations

from collections.abc import Iterator
from itertools import combinations

import numpy as np
import pandas as pd
import pyarrow as pa
import xxhash
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from flowrings.components import star_components
from flowrings.llm.arrow import byte_rows, documents_view
from flowrings.scratch import materialize

_ALL = (1 << 64) - 1


def fingerprint(raw: bytes, width: int = 3) -> int:
    """The unsigned fingerprint of a whole text: a bit is 1 if set in over half of the shingle hashes."""
    words = raw.lower().split()
    if not words:
        return 0
    text = b" ".join(words)
    n = len(words) - width + 1
    if n <= 1:
        hashes = np.array([xxhash.xxh64_intdigest(text, 42)], np.uint64)
    else:
        ends = np.cumsum(np.fromiter(map(len, words), np.int64, len(words)) + 1) - 1
        starts = np.concatenate([[0], ends[:-1] + 1])
        h = xxhash.xxh64_intdigest
        hashes = np.fromiter([h(text[s:e], 42) for s, e in zip(starts[:n].tolist(), ends[width - 1 :].tolist())], np.uint64, n)
    ones = np.unpackbits(hashes.view(np.uint8).reshape(-1, 8), axis=1, bitorder="little").sum(axis=0, dtype=np.int64)
    return int(np.packbits(ones * 2 > len(hashes), bitorder="little").view(np.uint64)[0])


def fingerprints(docs: DataFrame, id_col: str = "doc_id", text_col: str = "text", width: int = 3) -> DataFrame:
    """(doc_id, fp): fingerprints as signed 64-bit numbers."""

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in batches:
            rows = [(d, fingerprint(raw or b"", width)) for d, raw in byte_rows(batch, ["doc_id", "text"])]
            ids, fps = zip(*rows) if rows else ((), ())
            yield pa.RecordBatch.from_arrays([pa.array(ids, pa.int64()), pa.array(np.array(fps, np.uint64).view(np.int64))], ["doc_id", "fp"])

    return documents_view(docs, id_col, text_col).mapInArrow(run, "doc_id long, fp long")


def blocks() -> list[tuple[int, ...]]:
    """S(3,4,8): the 14 quadruples of 3-bit numbers whose exclusive or is zero."""
    return [q for q in combinations(range(8), 4) if q[0] ^ q[1] ^ q[2] ^ q[3] == 0]


def refine(mask: int) -> list[int]:
    """The masks that agree where ``mask`` does and in 4 of 8 equal pieces of the remaining bits."""
    free = [i for i in range(64) if not mask >> i & 1]
    size = len(free) // 8
    pieces = [sum(1 << i for i in free[p * size : (p + 1) * size]) for p in range(8)]
    return [mask | sum(pieces[p] for p in q) for q in blocks()]


def _signed(x: int) -> int:
    return x - (1 << 64) if x >> 63 else x


def tallied_pairs(fps: np.ndarray, least: int) -> tuple[np.ndarray, np.ndarray]:
    """Pairs (i < j) of distinct fingerprints that meet in at least ``least`` posting lists of (position, byte).

    A position in which all agree counts for every pair and needs no list.
    """
    n, table = len(fps), fps.view(np.uint8).reshape(-1, 8)
    if n == 2:  # most partitions: the lists of one pair are the positions in which it agrees
        met = np.zeros(int((table[0] == table[1]).sum() >= least), np.int64)
        return met, met + 1
    free = np.flatnonzero((table != table[0]).any(axis=0))
    least -= 8 - len(free)
    if least <= 0:
        return np.triu_indices(n, 1)
    met = []
    for p in free.tolist():
        order = np.argsort(table[:, p], kind="stable")
        for group in np.split(order, np.flatnonzero(np.diff(table[order, p])) + 1):
            if len(group) > 1:
                i, j = np.triu_indices(len(group), 1)
                met.append(group[i] * n + group[j])
    if not met:
        return np.empty(0, np.int64), np.empty(0, np.int64)
    pair, count = np.unique(np.concatenate(met), return_counts=True)
    return np.divmod(pair[count >= least], n)


def spanning_links(fps: np.ndarray, most_bits: int, min_shared: int) -> list[tuple[int, int]]:
    """A spanning forest of the links among distinct fingerprints (unsigned), as signed pairs."""
    a, b = tallied_pairs(fps, min_shared)
    near = np.bitwise_count(fps[a] ^ fps[b]) <= most_bits
    parent = list(range(len(fps)))

    def root(x: int) -> int:
        while parent[x] != x:
            parent[x] = x = parent[parent[x]]
        return x

    out, signed = [], fps.view(np.int64).tolist()
    for i, j in zip(a[near].tolist(), b[near].tolist()):
        i2, j2 = root(i), root(j)
        if i2 != j2:
            parent[max(i2, j2)] = min(i2, j2)
            out.append((signed[i], signed[j]))
    return out


def near_links(fps: DataFrame, most_bits: int = 3, longest: int = 256) -> DataFrame:
    """(a, b): links between distinct fingerprints (column fp) that connect all that lie within ``most_bits``.

    ``longest`` bounds the fingerprints that one task tallies at once; larger partitions are refined.
    """
    spark = fps.sparkSession
    if most_bits > 3:
        raise ValueError("the index covers at most 3 differing bits")

    def links(lists: pd.Series) -> pd.Series:
        return pd.Series([[{"a": a, "b": b} for a, b in spanning_links(np.array(x, np.int64).view(np.uint64), most_bits, 8 - most_bits)] for x in lists])

    to_links = F.pandas_udf(links, "array<struct<a: long, b: long>>")
    found, masks = None, [0]
    todo = fps.select("fp").withColumn("mask", F.lit(0).cast("long"))
    while masks:
        finer = {m: refine(m) for m in masks}
        table = spark.createDataFrame([(_signed(m), _signed(x)) for m, xs in finer.items() for x in xs], "mask long, finer long")
        lists = todo.join(F.broadcast(table), "mask").select(F.col("finer").alias("mask"), "fp", F.col("fp").bitwiseAND(F.col("finer")).alias("part"))
        sizes = materialize(lists.groupBy("mask", "part").count().filter("count > 1"), "posting-sizes")
        left = [x for xs in finer.values() for x in xs if x.bit_count() < 60]  # beyond it a list has 16 members at most
        short = sizes if not left else sizes.filter(F.col("count") <= longest)
        pairs = (
            lists.join(short.drop("count"), ["mask", "part"]).groupBy("mask", "part").agg(F.collect_list("fp").alias("fps"))
            .select(F.explode(to_links("fps")).alias("x")).select("x.a", "x.b")
        )
        pairs = materialize(pairs, "links")
        found = pairs if found is None else found.unionByName(pairs)
        long_lists = sizes.filter(F.col("count") > longest)
        masks = sorted({x & _ALL for r in long_lists.select("mask").distinct().collect() for x in [r[0]]}) if left else []
        if masks:
            todo = materialize(lists.join(long_lists.drop("count"), ["mask", "part"]).select("mask", "fp"), "long-lists")
    return found.distinct()


def near_components(docs: DataFrame, id_col: str = "doc_id", text_col: str = "text", most_bits: int = 3, width: int = 3, longest: int = 256) -> DataFrame:
    """One row per input row: doc_id, fingerprint (16 hex digits), component_id.

    Fingerprints link at ``most_bits`` or fewer differing bits; component_id is the least doc_id that
    links reach.  Texts without words (null, empty, blank) have fingerprint zero and link like others.
    Rows that repeat a doc_id get a row each, and the document joins the components of all its texts.
    """
    marked = materialize(fingerprints(docs, id_col, text_col, width), "fingerprints")
    nodes = materialize(marked.groupBy("fp").agg(F.min("doc_id").alias("least")), "distinct-fingerprints")
    roots = materialize(star_components(near_links(nodes, most_bits, longest), "a", "b"), "fingerprint-roots")
    joined = nodes.join(roots.withColumnRenamed("v", "fp"), "fp", "left").withColumn("root", F.coalesce("root", "fp"))
    joined = materialize(joined, "fingerprint-classes")
    least = materialize(joined.groupBy("root").agg(F.min("least").alias("component_id")), "component-ids")
    classes = materialize(joined.join(least, "root").select("fp", "component_id"), "classes")
    return marked.join(classes, "fp").select("doc_id", F.lower(F.lpad(F.hex("fp"), 16, "0")).alias("fingerprint"), "component_id")


def op1_simhash(spark: SparkSession, sf_dir: str) -> DataFrame:
    return near_components(spark.read.parquet(f"{sf_dir}/documents.parquet"))
