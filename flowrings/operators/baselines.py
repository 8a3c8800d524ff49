"""What the ring search is compared with."""

from __future__ import annotations

import numpy as np
import pandas as pd
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from flowrings.components import star_components
from flowrings.functions.stats import standardise
from flowrings.operators.louvain import detect_communities
from flowrings.params import LouvainParams
from flowrings.scratch import materialize


def serial_plain(edges: DataFrame) -> DataFrame:
    """Plain modularity on base weights, the whole graph in one task."""
    return detect_communities(edges, LouvainParams(objective="plain", weight="w_b", strategy="serial"))


def parallel_plain(edges: DataFrame, strategy: str = "sync", **changes) -> DataFrame:
    """Plain modularity on base weights, in parallel."""
    return detect_communities(edges, LouvainParams(objective="plain", weight="w_b", strategy=strategy, **changes))


def flow_and_time(edges: DataFrame, strategy: str = "sync", **changes) -> DataFrame:
    """Direction-aware modularity on final weights, in parallel."""
    return detect_communities(edges, LouvainParams(objective="flow", weight="w_e", strategy=strategy, **changes))


def in_times_out(edges: DataFrame, strategy: str = "local") -> DataFrame:
    """The rejected penalty k_in * k_out, on final weights."""
    return detect_communities(edges, LouvainParams(objective="inout", weight="w_e", strategy=strategy))


def _betweenness(near: dict[int, set[int]], members: list[int], cells: int = 2_000_000) -> dict[tuple[int, int], float]:
    """Shortest paths through each undirected edge among ``members``, a whole component (both directions counted once).

    All roots of a chunk go one step outwards at a time; a chunk has at most ``cells`` pairs of root and vertex.
    """
    ids = np.array(sorted(members))
    n = len(ids)
    degree = np.array([len(near[v]) for v in ids.tolist()])
    heads = np.searchsorted(ids, np.concatenate([np.array(sorted(near[v]), ids.dtype) for v in ids.tolist()]))
    tails, first = np.repeat(np.arange(n), degree), np.cumsum(degree) - degree
    flow = np.zeros(len(heads))
    for start in range(0, n, rows := max(1, cells // n)):
        roots = np.arange(start, min(n, start + rows))
        own = np.arange(len(roots)) * n
        depth, paths = np.full(len(roots) * n, -1, np.int32), np.zeros(len(roots) * n)
        front = own + roots
        depth[front], paths[front] = 0, 1.0
        steps, at = [], 0
        while len(front):
            v = front % n
            count = degree[v]
            arc = np.repeat(first[v] - np.cumsum(count) + count, count) + np.arange(count.sum())
            origin = np.repeat(front, count)
            goal = origin - tails[arc] + heads[arc]
            at += 1
            depth[goal[depth[goal] < 0]] = at
            ahead = depth[goal] == at
            arc, origin, goal = arc[ahead], origin[ahead], goal[ahead]
            front, place = np.unique(goal, return_inverse=True)
            paths[front] = np.bincount(place, paths[origin], len(front))
            steps.append((arc, origin, goal))
        credit = np.where(depth >= 0, 1.0, 0.0)
        for arc, origin, goal in reversed(steps):
            part = credit[goal] * paths[origin] / paths[goal]
            back, place = np.unique(origin, return_inverse=True)
            credit[back] += np.bincount(place, part, len(back))
            flow += np.bincount(arc, part, len(flow)) / 2
    out: dict[tuple[int, int], float] = {}
    for a, b, x in zip(ids[tails].tolist(), ids[heads].tolist(), flow.tolist()):
        key = (min(a, b), max(a, b))
        out[key] = out.get(key, 0.0) + x
    return out


def _pieces(near: dict[int, set[int]]) -> dict[int, int]:
    label: dict[int, int] = {}
    for v in sorted(near):
        if v not in label:
            todo = [v]
            label[v] = v
            while todo:
                for u in near[todo.pop()]:
                    if u not in label:
                        label[u] = v
                        todo.append(u)
    return label


def divide(pairs: list[tuple[int, int]]) -> dict[int, int]:
    """Cut the edge of highest betweenness again and again; the division of best unweighted modularity."""
    near: dict[int, set[int]] = {}
    for a, b in pairs:
        if a != b:
            near.setdefault(a, set()).add(b)
            near.setdefault(b, set()).add(a)
    links = [(a, b) for a in near for b in near[a] if a < b]
    degree, m = {v: len(x) for v, x in near.items()}, max(1, len(links))

    def quality(label: dict[int, int]) -> float:
        total: dict[int, int] = {}
        for v, c in label.items():
            total[c] = total.get(c, 0) + degree[v]
        return sum(label[a] == label[b] for a, b in links) / m - sum(t * t for t in total.values()) / (4 * m * m)

    label = _pieces(near)
    best, best_q = dict(label), quality(label)
    flow: dict[tuple[int, int], float] = {}
    stale = _groups(label)
    while any(near.values()):
        for members in stale:  # paths in other components are as they were
            if len(members) > 1:
                flow |= _betweenness(near, members)
        a, b = min(flow, key=lambda e: (-round(flow[e], 9), e))
        near[a].discard(b)
        near[b].discard(a)
        del flow[a, b]
        whole = _reached(near, a)
        stale = [whole] if b in whole else [whole, _reached(near, b)]
        if len(stale) == 2:
            for members in stale:
                label |= dict.fromkeys(members, min(members))
            if (q := quality(label)) > best_q + 1e-12:
                best, best_q = dict(label), q
    return best


def _reached(near: dict[int, set[int]], start: int) -> set[int]:
    seen, todo = {start}, [start]
    while todo:
        fresh = near[todo.pop()] - seen
        seen |= fresh
        todo += fresh
    return seen


def _groups(label: dict[int, int]) -> list[list[int]]:
    out: dict[int, list[int]] = {}
    for v, c in label.items():
        out.setdefault(c, []).append(v)
    return list(out.values())


def edge_betweenness(edges: DataFrame) -> DataFrame:
    """(v, comm) by divisive edge betweenness, one task per component (column mcs), whatever its size.

    After a cut only the paths of the component that was cut are counted again.  Work still grows as
    vertices times edges squared where a component does not fall apart.
    """
    def search(part: pd.DataFrame) -> pd.DataFrame:
        label = divide(list(zip(part.src.tolist(), part.dst.tolist())))
        return pd.DataFrame({"v": list(label), "comm": list(label.values())})

    return edges.select("mcs", "src", "dst").groupBy("mcs").applyInPandas(search, "v bigint, comm bigint")


def cliques(pairs: DataFrame, k: int) -> DataFrame:
    """(c): every k-clique of distinct pairs (a < b) as a sorted array.

    Pairs point from the end of smaller degree, so no vertex heads more than sqrt(2 E) of them.  A clique of
    one vertex more is two that agree in all but the last vertex, if those two are linked.
    """
    degree = pairs.select(F.explode(F.array("a", "b")).alias("v")).groupBy("v").agg(F.count(F.lit(1)).alias("deg"))
    wide = pairs.join(degree.select(F.col("v").alias("a"), F.col("deg").alias("da")), "a").join(degree.select(F.col("v").alias("b"), F.col("deg").alias("db")), "b")
    first = (F.col("da") < F.col("db")) | ((F.col("da") == F.col("db")) & (F.col("a") < F.col("b")))
    now = wide.select(F.array(F.when(first, F.col("a")).otherwise(F.col("b"))).alias("head"), F.when(first, F.col("b")).otherwise(F.col("a")).alias("y"))
    for _ in range(k - 2):
        now = materialize(now, "cliques")
        joined = now.join(now.withColumnRenamed("y", "z"), "head").filter("y < z")
        linked = joined.join(pairs.select(F.col("a").alias("y"), F.col("b").alias("z")), ["y", "z"], "left_semi")
        now = linked.select(F.concat("head", F.array("y")).alias("head"), F.col("z").alias("y"))
    return now.select(F.array_sort(F.concat("head", F.array("y"))).alias("c"))


def clique_percolation(edges: DataFrame, k: int = 3) -> DataFrame:
    """(v, comm, group): overlapping groups of k-cliques, each of which shares k - 1 vertices with another of its group.

    k = 2 gives the components.  Vertices in no clique belong to no group; a group is named by its least vertex.
    """
    if k < 2:
        raise ValueError("k is at least 2")
    pairs = edges.filter("src <> dst").select(F.least("src", "dst").alias("a"), F.greatest("src", "dst").alias("b")).distinct()
    pairs = materialize(pairs, "pairs")
    if k == 2:
        return star_components(pairs, "a", "b", local_edges=200_000).select("v", F.col("root").alias("comm"), F.col("root").alias("group"))
    found = materialize(cliques(pairs, k).select("c", F.xxhash64("c").alias("id")), "k-cliques")
    without = F.array(*(F.xxhash64(F.concat(F.slice("c", 1, i), F.slice("c", i + 2, k))) for i in range(k)))
    sides = found.select("id", F.explode(without).alias("side"))
    least = sides.groupBy("side").agg(F.min("id").alias("root"))
    joined = star_components(sides.join(least, "side").select("id", "root"), "id", "root", local_edges=200_000)
    members = found.join(joined.withColumnRenamed("v", "id"), "id").select("root", F.explode("c").alias("v")).distinct()
    names = members.groupBy("root").agg(F.min("v").alias("comm"))
    return members.join(names, "root").select("v", "comm", F.col("root").alias("group"))


def rules(edges: DataFrame, amount: float = 300_000.0, times: int = 3) -> DataFrame:
    """Edges flagged by thresholds on money or times: the rule-based screen."""
    return edges.filter((F.col("money") >= amount) | (F.col("times") >= times)).select(
        "src", "dst", "money", "times", F.concat_ws(",", F.when(F.col("money") >= amount, "amount"), F.when(F.col("times") >= times, "times")).alias("rule")
    )


def account_outliers(vertices: DataFrame, z: float = 3.0) -> DataFrame:
    """Accounts with a standardised money, number of transfers or degree beyond ``z``: the single-account screen."""
    scored = standardise(vertices, ["money", "times", "deg"])
    worst = F.greatest("z_money", "z_times", "z_deg")
    return scored.withColumn("worst", worst).filter(F.col("worst") > z).select("v", "deg", "money", "times", "worst")
