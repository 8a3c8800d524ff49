"""Community search: component by component, or in synchronous rounds over the whole graph.

Communities never cross a connected component, and apart from 2m the gain of a move involves only sums
of the communities next to a vertex.  So after screening (components of bounded size) the serial search
runs on each component by itself: one shuffle in all.  Components beyond a bound take synchronous
rounds, in which every vertex decides from the labels of the round before.  A round is two jobs: one
decides all moves and measures the state it starts from, one repairs and applies them.  Rounds end when no
label changes or modularity has not risen for ``STALE`` rounds; bounds that end them earlier are logged and
warned of.  A synchronous search of at most ``local_edges`` edges (counted first) does its rounds in one
task, with the same result.
"""

from __future__ import annotations

import warnings
from collections.abc import Iterator
from dataclasses import dataclass, field

import numpy as np
import pandas as pd
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from flowrings.operators.compress import carried_sums, compress
from flowrings.operators.graph import connected_components, with_component
from flowrings.operators.kernel import EPS, serial_louvain, synchronous_louvain, tie_digits
from flowrings.operators.modularity import Prepared, prepare
from flowrings.operators.repairs import follow_moves, owner_targets, undo_swaps, without_swaps
from flowrings.params import LouvainParams
from flowrings.scratch import materialize, materialize_observed, release


#: Rounds without a rise of modularity after which a level is taken to oscillate.
STALE = 3


@dataclass
class RoundLog:
    """What each synchronous round did: (level, round, moves, swaps, followed, q, stop).

    ``stop`` says why a level ended with this round: 'settled' (no label changes), 'no gain', or
    'round bound'.  A row without a round, stop 'level bound', says that ``max_levels`` ended the search.
    """

    rows: list[tuple] = field(default_factory=list)


def singletons(state: DataFrame) -> DataFrame:
    return state.withColumn("comm", F.col("v"))


def community_totals(state: DataFrame) -> DataFrame:
    """(comm, sum_x, sum_y) over all members."""
    return state.groupBy("comm").agg(F.sum("x").alias("sum_x"), F.sum("y").alias("sum_y"))


def neighbour_info(edges: DataFrame, state: DataFrame) -> DataFrame:
    """(v, info): for each vertex the records of all its neighbours, gathered into an array.

    The literal form of the neighbour exchange, for cross-checks on small graphs: a hub's array is as
    long as its neighbourhood.  ``state`` has v, k, k_in, k_out, comm.
    """
    fields = ["k", "k_in", "k_out", "comm"]
    side = lambda v, p: state.select(F.col("v").alias(v), *(F.col(c).alias(f"{c}_{p}") for c in fields))
    pairs = edges.select(F.explode(F.array(F.struct(F.col("src").alias("v"), F.col("dst").alias("u")), F.struct(F.col("dst").alias("v"), F.col("src").alias("u")))).alias("x")).select("x.*").distinct()
    wide = pairs.join(side("v", "i"), "v").join(side("u", "j"), "u")
    return wide.groupBy("v").agg(F.array_sort(F.collect_list(F.struct("u", *(f"{c}_{p}" for p in "ij" for c in fields)))).alias("info"))


def scores(prepared: Prepared, state: DataFrame, params: LouvainParams = LouvainParams(), theta_scope: str = "community", links: DataFrame | None = None) -> DataFrame:
    """(v, cand, x, y, k, sum_y, score, own): the gain of every vertex in every neighbouring community and in its own.

    ``theta_scope='neighbours'`` takes the penalty of a community over the vertex's neighbours only.  ``links``
    may be the prepared ones in a layout that suits the join with the neighbours' labels.
    """
    links = prepared.links if links is None else links
    there = state.select(F.col("v").alias("u"), F.col("comm").alias("cand"), F.col("x").alias("ux"), F.col("y").alias("uy"))
    pull = links.join(there, "u").select("v", "cand", "a", "x", "y", "ux", "uy", F.lit(False).alias("own"))
    zero = F.lit(0.0)
    mine = state.select("v", F.col("comm").alias("cand"), zero.alias("a"), "x", "y", zero.alias("ux"), zero.alias("uy"), F.lit(True).alias("own"))
    wide = pull.unionByName(mine).groupBy("v", "cand").agg(
        F.max("x").alias("x"), F.max("y").alias("y"), F.sum("a").alias("k"), F.sum("ux").alias("nx"), F.sum("uy").alias("ny"), F.max("own").alias("own")
    )
    wide = wide.join(community_totals(state).withColumnRenamed("comm", "cand"), "cand")
    if theta_scope == "community":
        big_x, big_y = F.col("sum_x") - F.when(F.col("own"), F.col("x")).otherwise(0.0), F.col("sum_y") - F.when(F.col("own"), F.col("y")).otherwise(0.0)
    else:
        big_x, big_y = F.col("nx"), F.col("ny")
    two_m, factor = F.lit(float(prepared.two_m)), 2.0 if params.gain == "exact" else 1.0
    score = F.lit(factor) * F.col("k") / two_m - F.lit(params.resolution) * (F.col("x") * big_y + F.col("y") * big_x) / (two_m * two_m)
    return wide.select("v", "cand", "x", "y", "k", "sum_y", F.round(score, tie_digits(prepared.n_edges)).alias("score"), "own")


def decisions(prepared: Prepared, state: DataFrame, params: LouvainParams = LouvainParams(), theta_scope: str = "community", links: DataFrame | None = None) -> DataFrame:
    """(v, x, y, old, new, gain, inner, pen) of every vertex; new is null where it stays, ties go to the least label.

    inner and pen are the vertex's part of the weight inside communities and of their penalties.
    """
    mine = F.col("own")
    best = scores(prepared, state, params, theta_scope, links).groupBy("v").agg(
        F.max("x").alias("x"), F.max("y").alias("y"), F.max(F.struct("score", (-F.col("cand")).alias("neg"))).alias("best"),
        *(F.max(F.when(mine, F.col(c))).alias(n) for c, n in (("score", "stay"), ("cand", "old"), ("k", "inner"), ("sum_y", "sum_y"))),
    )
    new, gain = -F.col("best.neg"), F.col("best.score") - F.col("stay")
    goes = (gain > 10.0 ** -tie_digits(prepared.n_edges)) & (new != F.col("old"))
    return best.select("v", "x", "y", "old", F.when(goes, new).alias("new"), gain.alias("gain"), "inner", (F.col("x") * F.col("sum_y")).alias("pen"))


def parallel_round(prepared: Prepared, state: DataFrame, params: LouvainParams = LouvainParams(), theta_scope: str = "community") -> DataFrame:
    """(v, old, new, gain) of the vertices that move; ties go to the least label."""
    return decisions(prepared, state, params, theta_scope).filter("new IS NOT NULL").select("v", "old", "new", "gain")


def _apply(decided: DataFrame, params: LouvainParams, number: int, n_vertices: int) -> tuple[DataFrame, dict]:
    """The state after a round, and what was changed, followed and swapped."""
    moves = decided.filter("new IS NOT NULL").select("v", "x", "y", "old", "new")
    if params.damping:
        moves = moves.filter(F.pmod(F.xxhash64("v", F.lit(number)), F.lit(2)) == 0)
    if params.repair == "round":
        moves = without_swaps(moves, params.swap_rule)
        kept = moves.filter("stands").select("v", "old", "new")
        owners = kept.filter("v = old").select(F.col("v").alias("label"), F.col("new").alias("target"))
        ends = owners if params.lag_hops == 1 else owner_targets(owners, n_vertices)
        moves = moves.join(ends.withColumnRenamed("label", "new"), "new", "left")
    else:
        moves = moves.withColumns({"crossed": F.lit(False), "stands": F.lit(True), "target": F.lit(None).cast("long")})
    to = F.when(F.col("stands"), F.coalesce("target", "new")).otherwise(F.col("old"))
    moved = moves.select("v", "x", "y", to.alias("comm"), (to != F.col("old")).alias("changed"), (F.col("stands") & F.coalesce(F.col("target") != F.col("new"), F.lit(False))).alias("followed"), "crossed")
    no = F.lit(False)
    rest = decided.filter("new IS NULL")
    if params.damping:
        rest = decided.join(moves.select("v"), "v", "left_anti")
    rest = rest.select("v", "x", "y", F.col("old").alias("comm"), no.alias("changed"), no.alias("followed"), no.alias("crossed"))
    return materialize_observed(moved.unionByName(rest), "state", changed=F.count_if("changed"), followed=F.count_if("followed"), swaps=F.count_if("crossed"))


def rounds(prepared: Prepared, params: LouvainParams, n: int) -> DataFrame:
    """(v, comm) after ``n`` synchronous rounds from singletons, each repaired, whatever they do to Q."""
    state = singletons(prepared.state)
    for number in range(n):
        state, _ = _apply(materialize(decisions(prepared, state, params), "decisions"), params, number, prepared.n_vertices)
    return state.select("v", "comm")


def stage_one(prepared: Prepared, params: LouvainParams, log: RoundLog, level: int) -> tuple[DataFrame, float]:
    """Synchronous rounds until nothing moves or ``max_rounds``: the best state seen (v, x, y, comm, ...) and its Q."""
    spark = prepared.links.sparkSession
    links = prepared.links.repartition(int(spark.conf.get("spark.sql.shuffle.partitions")), "u").persist()
    state, best, best_q, stale, number, did = singletons(prepared.state), None, 0.0, 0, 0, None
    try:
        while True:
            decided, seen = materialize_observed(
                decisions(prepared, state, params, links=links), "decisions", moves=F.count("new"), inner=F.sum("inner"), pen=F.sum("pen")
            )
            q = (seen["inner"] + 2 * prepared.loops) / prepared.two_m - params.resolution * seen["pen"] / prepared.two_m**2
            if did is None:
                best, best_q = state, q
            else:
                if q > best_q + EPS:
                    release(best)
                    best, best_q, stale = state, q, 0
                else:
                    stale += 1
                stop = "settled" if did["changed"] == 0 else "no gain" if stale >= STALE else "round bound" if number == params.max_rounds else None
                log.rows.append((level, number - 1, did["moves"], did["swaps"], did["followed"], q, stop))
                if stop:
                    break
            if seen["moves"] == 0:
                log.rows.append((level, number, 0, 0, 0, best_q, "settled"))
                break
            before = state
            state, did = _apply(decided, params, number, prepared.n_vertices)
            did = {**did, "moves": seen["moves"]}
            number += 1
            release(decided, *([before] if before is not best else []))
    finally:
        links.unpersist()
    release(decided, *([state] if state is not best else []))
    if params.repair == "stage":
        moved = best.filter("v <> comm").select("v", F.col("v").alias("old"), F.col("comm").alias("new"))
        fixed = follow_moves(undo_swaps(moved), params.lag_hops).select("v", F.col("new").alias("fixed"))
        best = materialize(best.select("v", "x", "y").join(fixed, "v", "left").select("v", "x", "y", F.coalesce("fixed", "v").alias("comm")), "state")
        best_q = partition_quality(prepared, best, params.resolution)
    return best, best_q


def partition_quality(prepared: Prepared, state: DataFrame, resolution: float = 1.0) -> float:
    """Q of any state (v, x, y, comm), from its own scores."""
    seen = decisions(prepared, state, LouvainParams(resolution=resolution)).agg(F.sum("inner").alias("inner"), F.sum("pen").alias("pen")).first()
    return (seen["inner"] + 2 * prepared.loops) / prepared.two_m - resolution * seen["pen"] / prepared.two_m**2


def _synchronous(edges: DataFrame, params: LouvainParams, log: RoundLog, totals: tuple[float, int] | None = None) -> DataFrame:
    """(v, level, comm) of every level.  ``totals`` are those of a larger graph that ``edges`` are part of."""
    now = edges.select("src", "dst", F.col(params.weight).cast("double").alias("w"))
    prepared = prepare(now, "w", params.objective)
    totals = (prepared.two_m, prepared.n_edges) if totals is None else totals
    labels = materialize(prepared.state.select("v", F.col("v").alias("comm")), "labels")
    levels, last = [], None
    for level in range(params.max_levels):
        prepared.two_m, prepared.n_edges = totals
        if prepared.two_m <= 0 or prepared.n_vertices == 0:
            break
        state, q = stage_one(prepared, params, log, level)
        if last is not None and q <= last + 1e-9:
            break
        settled = state.filter("v <> comm").isEmpty()
        last = q
        step = state.select("v", "comm")
        labels = materialize(labels.join(step.select(F.col("v").alias("comm"), F.col("comm").alias("up")), "comm").select("v", F.col("up").alias("comm")), "labels")
        levels.append(labels.select("v", F.lit(level).alias("level"), "comm"))
        if settled:
            break
        if level + 1 == params.max_levels:
            log.rows.append((level, None, None, None, None, q, "level bound"))
            break
        before, now = now, materialize(compress(now, step), "compressed")
        carried = carried_sums(prepared.state, step) if params.delta_mode == "carried" else None
        old, prepared = prepared, prepare(now, "w", params.objective, carried)
        release(before, old.links, old.state, state)
    if not levels:
        levels = [labels.select("v", F.lit(0).alias("level"), "comm")]
    out = levels[0]
    for x in levels[1:]:
        out = out.unionByName(x)
    return out


def _synchronous_small(edges: DataFrame, params: LouvainParams, log: RoundLog) -> DataFrame:
    """``_synchronous`` by one task."""
    kw = dict(kind=params.objective, gain=params.gain, resolution=params.resolution, delta_mode=params.delta_mode, swap_rule=params.swap_rule, lag_hops=params.lag_hops, stale_rounds=STALE, max_rounds=params.max_rounds, max_levels=params.max_levels)

    def search(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        parts = [[c.to_numpy() for c in b.columns] for b in batches] or [[np.empty(0, np.int64), np.empty(0, np.int64), np.empty(0)]]
        src, dst, w = (np.concatenate(x) for x in zip(*parts))
        order = np.lexsort((w, dst, src))
        ids, levels, rows = synchronous_louvain(src[order], dst[order], w[order], **kw)
        size = len(ids) * len(levels)
        cols = list(zip(*rows)) or [()] * 7
        found = [np.tile(ids, len(levels)), np.repeat(np.arange(len(levels)), len(ids)), np.concatenate(levels), *[[None] * size] * 6]
        for x in (found, [[None] * len(rows), cols[0], [None] * len(rows), *cols[1:]]):
            yield pa.RecordBatch.from_arrays([pa.array(c, t) for c, t in zip(x, types)], names)

    types, names = [pa.int64(), pa.int32(), pa.int64(), *[pa.int64()] * 4, pa.float64(), pa.string()], ["v", "level", "comm", "round", "moves", "swaps", "followed", "q", "stop"]
    rows = edges.select(F.col("src").cast("long").alias("src"), F.col("dst").cast("long").alias("dst"), F.col(params.weight).cast("double").alias("w")).filter("w > 0").coalesce(1)
    out = materialize(rows.mapInArrow(search, "v long, level int, comm long, round long, moves long, swaps long, followed long, q double, stop string"), "synchronous")
    did = out.filter("v IS NULL").select("level", "round", "moves", "swaps", "followed", "q", "stop").collect()  # a row a round
    log.rows.extend(tuple(r) for r in sorted(did, key=lambda r: (r["level"], r["round"] is None, r["round"])))
    return out.filter("v IS NOT NULL").select("v", "level", "comm")


def _warn_of_bounds(log: RoundLog) -> None:
    if hit := sorted({r[-1] for r in log.rows if r[-1] in ("round bound", "level bound")}):
        warnings.warn(f"the synchronous search was ended by its {' and '.join(hit)}, not by convergence", stacklevel=3)


def canonical(levels: DataFrame) -> DataFrame:
    """Name every community of every level by its least member."""
    least = levels.groupBy("level", "comm").agg(F.min("v").alias("least"))
    return levels.join(least, ["level", "comm"]).select("v", "level", F.col("least").alias("comm"))


def _local(edges: DataFrame, params: LouvainParams, two_m: float, n_edges: int, by: str = "mcs") -> DataFrame:
    """(v, level, comm): the serial search on each component, one task per component."""
    kw = dict(kind=params.objective, two_m=two_m, gain=params.gain, resolution=params.resolution, delta_mode=params.delta_mode, max_rounds=params.max_rounds * 5, max_levels=params.max_levels, digits=tie_digits(n_edges))

    def search(part: pd.DataFrame) -> pd.DataFrame:
        part = part.sort_values(["src", "dst"])
        ids, levels = serial_louvain(part.src.to_numpy(), part.dst.to_numpy(), part.w.to_numpy(), **kw)
        n = len(ids)
        return pd.DataFrame({"v": np.tile(ids, len(levels)), "level": np.repeat(np.arange(len(levels), dtype=np.int32), n), "comm": np.concatenate(levels)})

    rows = edges.select(by, "src", "dst", F.col(params.weight).cast("double").alias("w")).filter("w > 0")
    return rows.groupBy(by).applyInPandas(search, "v bigint, level int, comm bigint")


def detect_levels(edges: DataFrame, params: LouvainParams = LouvainParams(), log: RoundLog | None = None) -> DataFrame:
    """(v, level, comm): the dendrogram.  ``edges`` has src, dst, the weight and, where known, mcs.

    Levels of components differ in number; a vertex keeps its last community beyond them (``detect_communities``).
    Vertices whose edges all have weight zero are left out.
    """
    log = RoundLog() if log is None else log
    if params.strategy == "sync":
        small = not params.damping and params.repair == "round" and edges.count() <= params.local_edges
        levels = (_synchronous_small if small else _synchronous)(edges, params, log)
        _warn_of_bounds(log)
        return canonical(levels)
    if params.strategy == "serial":
        whole = edges.withColumn("mcs", F.lit(0).cast("bigint"))
        return _local(whole, params, *_totals(edges, params))
    if "mcs" not in edges.columns:
        edges = with_component(edges, connected_components(edges))
    two_m, n_edges = _totals(edges, params)
    if params.strategy == "local":
        return _local(edges, params, two_m, n_edges)
    edges = materialize(edges.select("mcs", "src", "dst", params.weight), "component-edges")
    large = edges.groupBy("mcs").count().filter(F.col("count") > params.local_edges).select("mcs")
    large = materialize(large, "large-components")
    small = _local(edges.join(large, "mcs", "left_anti"), params, two_m, n_edges)
    if large.isEmpty():
        return small
    levels = _synchronous(edges.join(large, "mcs", "left_semi"), params, log, (two_m, n_edges))
    _warn_of_bounds(log)
    return small.unionByName(canonical(levels))


def _totals(edges: DataFrame, params: LouvainParams) -> tuple[float, int]:
    """Twice the total weight, and the number of edges with weight."""
    w = F.col(params.weight).cast("double")
    total, n = edges.agg(F.coalesce(F.sum(w), F.lit(0.0)), F.count_if(w > 0)).first()
    return 2 * total, n


def unfold(levels: DataFrame) -> DataFrame:
    """(v, path, comm): the community at each level as an array, and the last one."""
    path = F.transform(F.array_sort(F.collect_list(F.struct("level", "comm"))), lambda x: x["comm"])
    return levels.groupBy("v").agg(path.alias("path")).withColumn("comm", F.element_at("path", -1))


def detect_communities(edges: DataFrame, params: LouvainParams = LouvainParams(), log: RoundLog | None = None) -> DataFrame:
    """(v, comm): the last level, communities named by their least member."""
    levels = detect_levels(edges, params, log)
    return levels.groupBy("v").agg(F.max_by("comm", "level").alias("comm"))
