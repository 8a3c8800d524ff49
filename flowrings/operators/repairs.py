"""Repairs of a synchronous round: moves that crossed, and moves after an owner that left.

Labels are vertex ids, so a label has an owner: the vertex (or super-vertex) of that id.  Both repairs
look at moved rows (v, old, new) only.
"""

from __future__ import annotations

from collections.abc import Iterator

import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from flowrings.operators.kernel import follow_owners
from flowrings.scratch import materialize


def undo_swaps(moves: DataFrame) -> DataFrame:
    """Moves without those whose target community sent a vertex to their own old community: both stay."""
    crossed = moves.select(F.col("new").alias("old"), F.col("old").alias("new")).distinct()
    return moves.join(crossed, ["old", "new"], "left_anti").select("v", "old", "new")


def mark_crossed(moves: DataFrame) -> DataFrame:
    """Moves with column crossed: whether their target community sent a vertex back.

    Pairs of communities are reduced to one row before they meet the moves, however many vertices they exchange.
    """
    low, high = F.least("old", "new").alias("low"), F.greatest("old", "new").alias("high")
    pairs = moves.groupBy(low, high).agg(F.max(F.col("old") < F.col("new")).alias("up"), F.max(F.col("old") > F.col("new")).alias("down"))
    pairs = pairs.select("low", "high", (F.col("up") & F.col("down")).alias("crossed"))
    return moves.select("*", low, high).join(pairs, ["low", "high"]).drop("low", "high")


def without_swaps(moves: DataFrame, rule: str) -> DataFrame:
    """Moves with column stands: what is left of crossed ones.

    ``'undo'`` sends both sides back, as published; they may choose the same again in every later round.
    ``'smaller'`` lets the move to the smaller label stand, so the two communities meet at once.
    """
    if rule not in ("undo", "smaller"):
        raise ValueError("swap_rule is 'undo' or 'smaller'")
    stands = ~F.col("crossed") if rule == "undo" else ~F.col("crossed") | (F.col("new") < F.col("old"))
    return mark_crossed(moves).withColumn("stands", stands)


def follow_moves(moves: DataFrame, hops: int | str = "closure", at_most: int | None = None) -> DataFrame:
    """A vertex that joined a community whose owner left for another follows the owner.

    ``hops=1`` is a single step; with ``'closure'`` chains are followed to their end by pointer
    doubling, and everyone in or behind a cycle of owners takes the cycle's least label.  ``at_most``
    is a known bound on the number of owners, which saves counting them.
    """
    owners = moves.filter("v = old").select(F.col("v").alias("label"), F.col("new").alias("target"))
    if hops == 1:
        return _redirect(moves, owners)
    return _redirect(moves, owner_targets(owners, at_most))


def owner_targets(owners: DataFrame, at_most: int | None = None, local_rows: int = 200_000) -> DataFrame:
    """(label, target) with every chain followed to its end; the labels of a cycle go to the least of them.

    After k doublings a pointer has gone 2**k steps and knows the least label on its way.  The chain of
    m owners is at an end, or at least once around its cycle, when 2**k >= m.  At most ``local_rows``
    owners (counted first) are followed by one task instead.
    """
    n = owners.count() if at_most is None else at_most
    if n <= local_rows:
        return owners.coalesce(1).mapInArrow(_chase, "label long, target long")
    owners = materialize(owners, "owners")
    now = owners.select("label", "target", F.col("target").alias("least"))
    steps = 1
    while steps < 2 * max(1, n):
        ahead = now.select(F.col("label").alias("target"), F.col("target").alias("next"), F.col("least").alias("further"))
        joined = now.join(ahead, "target", "left")
        now = materialize(joined.select("label", F.coalesce("next", "target").alias("target"), F.least("least", F.coalesce("further", "least")).alias("least")), "pointers")
        steps *= 2
    # still on an owner: on a cycle, whose least label is what a pointer that started there has met
    ends = now.join(now.select(F.col("label").alias("target"), F.col("least").alias("around")), "target", "left")
    return ends.select("label", F.coalesce("around", "target").alias("target"))


def _redirect(moves: DataFrame, targets: DataFrame) -> DataFrame:
    to = targets.select(F.col("label").alias("new"), "target")
    return moves.join(to, "new", "left").select("v", "old", F.coalesce("target", "new").alias("new"))


def _chase(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
    """Ends of all chains of one partition's owners."""
    to = {a: b for batch in batches for a, b in zip(batch.column(0).to_pylist(), batch.column(1).to_pylist())}
    end = follow_owners(to)
    yield pa.RecordBatch.from_arrays([pa.array(list(end), pa.int64()), pa.array(list(end.values()), pa.int64())], ["label", "target"])
