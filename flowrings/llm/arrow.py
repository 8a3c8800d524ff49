"""Helpers for operators that run Python over Arrow batches of whole texts."""

from __future__ import annotations

import ctypes
import gc
import sys
from collections.abc import Callable, Iterator

import pyarrow as pa
from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F


def documents_view(docs: DataFrame, id_col: str = "doc_id", text_col: str = "text") -> DataFrame:
    """Only the id and the text, under fixed names: other columns of the caller cannot clash."""
    return docs.select(F.col(f"`{id_col}`").alias("doc_id"), F.col(f"`{text_col}`").alias("text"))


def map_rows(df: DataFrame, row: Callable, schema: str, columns: list[str]) -> DataFrame:
    """``row(*values) -> tuple`` for every row; strings come as UTF-8 bytes (None where null)."""
    names = [x.split()[0] for x in schema.split(", ")]

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        types = {n: _arrow_type(x.split()[1]) for n, x in zip(names, schema.split(", "))}
        for batch in batches:
            out = [row(*values) for values in byte_rows(batch, columns)]
            cols = list(zip(*out)) if out else [()] * len(names)
            yield pa.RecordBatch.from_arrays([pa.array(c, types[n]) for n, c in zip(names, cols)], names)

    return df.select(*columns).mapInArrow(run, schema)


def small_batches(batches: Iterator[pa.RecordBatch], rows: int = 500) -> Iterator[pa.RecordBatch]:
    """The same rows in batches of at most ``rows``: what Python makes of the texts at once, or sends back, stays small."""
    for batch in batches:
        for start in range(0, batch.num_rows, rows):
            yield batch.slice(start, rows)


def give_back_memory() -> None:
    """Return what a task has freed to the system: a Python worker outlives its task and idles beside later ones."""
    gc.collect()
    pa.default_memory_pool().release_unused()
    if sys.platform == "linux" and hasattr(libc := ctypes.CDLL(None), "malloc_trim"):
        libc.malloc_trim(0)


def keep_rows(df: DataFrame, test: Callable[[bytes | None], bool], text_col: str = "text") -> DataFrame:
    """The rows, with all their columns, whose text (as UTF-8 bytes) passes; nothing is shuffled."""

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        try:
            for batch in small_batches(batches):
                yield batch.filter(pa.array([test(raw) for (raw,) in byte_rows(batch, [text_col])], pa.bool_()))
        finally:
            give_back_memory()

    return df.mapInArrow(run, df.schema)


def byte_rows(batch: pa.RecordBatch, columns: list[str]) -> Iterator[tuple]:
    """Rows of a batch, one at a time, with strings as UTF-8 bytes."""
    arrays = []
    for c in columns:
        a = batch.column(batch.schema.get_field_index(c))
        arrays.append(a.cast(pa.binary()) if pa.types.is_string(a.type) else a)
    for i in range(batch.num_rows):
        yield tuple(a[i].as_py() for a in arrays)


def _arrow_type(name: str) -> pa.DataType:
    return {
        "long": pa.int64(), "int": pa.int32(), "double": pa.float64(), "string": pa.string(),
        "boolean": pa.bool_(), "binary": pa.binary(), "array<string>": pa.list_(pa.string()),
        "array<int>": pa.list_(pa.int32()), "array<double>": pa.list_(pa.float64()),
    }[name]


def held_out(id_col: str = "doc_id") -> Column:
    """True for the documents that models must not learn from: crc32 of the id as text, mod 4, is 2."""
    return F.coalesce(F.crc32(F.col(id_col).cast("string")) % 4 == 2, F.lit(False))
