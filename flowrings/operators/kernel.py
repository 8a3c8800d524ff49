"""Serial Louvain in one task: the reference search, and the kernel for single components."""

from __future__ import annotations

import numpy as np

EPS = 1e-12


def tie_digits(n_edges: int) -> int:
    """Decimals to which gains are compared: 12 up to a million edges, one more for each further power of ten.

    The gain of one vertex is of the order of its share of the total weight, so fixed decimals would make
    all moves of a very large graph ties.
    """
    return 12 + max(0, len(str(max(1, n_edges) - 1)) - 6)


def vertex_numbers(src: np.ndarray, dst: np.ndarray, w: np.ndarray, n: int, kind: str) -> tuple[np.ndarray, np.ndarray]:
    k_in, k_out = np.bincount(dst, w, n), np.bincount(src, w, n)
    k = k_in + k_out
    if kind == "plain":
        return k, k.copy()
    if kind == "inout":
        return k_in, 4 * k_out
    skew = np.divide(k_in - k_out, k, out=np.zeros(n), where=k > 0)
    return k * np.exp(skew), k * np.exp(-skew)


def _adjacency(src, dst, w, n):
    near = [{} for _ in range(n)]
    for a, b, x in zip(src.tolist(), dst.tolist(), w.tolist()):
        if a != b:
            near[a][b] = near[a].get(b, 0.0) + x
            near[b][a] = near[b].get(a, 0.0) + x
    return near


def local_moving(near: list[dict], x: list, y: list, two_m: float, *, gain: str = "exact", resolution: float = 1.0, max_rounds: int = 50, digits: int = 12) -> tuple[list[int], int]:
    """Visit vertices in order of id, move each to the best neighbouring community, until none moves."""
    n = len(near)
    comm, x_of, y_of = list(range(n)), list(x), list(y)
    factor, scale, eps = 2.0 if gain == "exact" else 1.0, resolution / two_m**2, 10.0**-digits
    for rounds in range(1, max_rounds + 1):
        moved = False
        for i in range(n):
            own, xi, yi = comm[i], x[i], y[i]
            links: dict[int, float] = {own: 0.0}
            for j, a in near[i].items():
                links[comm[j]] = links.get(comm[j], 0.0) + a
            x_of[own] -= xi
            y_of[own] -= yi
            score = {c: factor * k / two_m - scale * (xi * y_of[c] + yi * x_of[c]) for c, k in links.items()}
            best = min(score, key=lambda c: (-round(score[c], digits), c))
            if score[best] <= score[own] + eps:
                best = own
            x_of[best] += xi
            y_of[best] += yi
            if best != own:
                comm[i], moved = best, True
        if not moved:
            return comm, rounds
    return comm, max_rounds


def quality(src, dst, w, comm: np.ndarray, x, y, two_m: float, resolution: float = 1.0) -> float:
    """Q of a partition, from the factorised form."""
    inner = 2 * w[comm[src] == comm[dst]].sum()
    size = int(comm.max()) + 1 if len(comm) else 0
    return float(inner / two_m - resolution * (np.bincount(comm, x, size) * np.bincount(comm, y, size)).sum() / two_m**2)


def serial_louvain(
    src: np.ndarray, dst: np.ndarray, w: np.ndarray, *, kind: str = "flow", two_m: float | None = None, gain: str = "exact", resolution: float = 1.0,
    delta_mode: str = "carried", max_rounds: int = 50, max_levels: int = 20, digits: int | None = None,
) -> tuple[np.ndarray, list[np.ndarray]]:
    """Vertex ids in ascending order, and for each level the community of each (its least member's id)."""
    ids, ends = np.unique(np.concatenate([src, dst]), return_inverse=True)
    s, d, w = ends[: len(src)], ends[len(src) :], np.asarray(w, float)
    n = len(ids)
    if two_m is None:
        two_m = 2 * float(w.sum())
    digits = tie_digits(len(w)) if digits is None else digits
    place, levels = np.arange(n), []
    if n == 0 or two_m <= 0:
        return ids, [ids.copy()]
    x, y = vertex_numbers(s, d, w, n, kind)
    best = -np.inf
    for _ in range(max_levels):
        comm, _ = local_moving(_adjacency(s, d, w, n), x.tolist(), y.tolist(), two_m, gain=gain, resolution=resolution, max_rounds=max_rounds, digits=digits)
        names, comm = np.unique(np.array(comm), return_inverse=True)
        q = quality(s, d, w, comm, x, y, two_m, resolution)
        if q <= best + 1e-9 and levels:
            break
        best, place = q, comm[place]
        least = np.full(len(names), np.iinfo(np.int64).max)
        np.minimum.at(least, place, ids)
        levels.append(least[place])
        if len(names) == n:
            break
        s, d, n = comm[s], comm[d], len(names)
        key, inverse = np.unique(s * n + d, return_inverse=True)
        w, s, d = np.bincount(inverse, w), key // n, key % n
        if delta_mode == "carried":
            x, y = np.bincount(comm, x, n), np.bincount(comm, y, n)
        else:
            x, y = vertex_numbers(s, d, w, n, kind)
    return ids, levels


def follow_owners(owners: dict[int, int]) -> dict[int, int]:
    """Where every chain of owners (label to target) ends; the labels of a cycle go to the least of them."""
    end: dict[int, int] = {}
    for start in owners:
        path, on_path, now = [], {}, start
        while now in owners and now not in end and now not in on_path:
            on_path[now] = len(path)
            path.append(now)
            now = owners[now]
        last = min(path[on_path[now] :]) if now in on_path else end.get(now, now)
        end |= dict.fromkeys(path, last)
    return end


def synchronous_moves(v, u, a, comm, x, y, two_m: float, gain: str, resolution: float, digits: int = 12) -> tuple[np.ndarray, np.ndarray]:
    """Vertices that move and their new communities, decided from the labels ``comm``; ties go to the least label."""
    n = len(comm)
    key, inverse = np.unique(np.concatenate([v * n + comm[u], np.arange(n) * n + comm]), return_inverse=True)
    k = np.bincount(inverse, np.concatenate([a, np.zeros(n)]), len(key))
    i, c = key // n, key % n
    own = comm[i] == c
    big_x, big_y = np.bincount(comm, x, n)[c] - np.where(own, x[i], 0.0), np.bincount(comm, y, n)[c] - np.where(own, y[i], 0.0)
    factor = 2.0 if gain == "exact" else 1.0
    score = np.round(factor * k / two_m - resolution * (x[i] * big_y + y[i] * big_x) / two_m**2, digits)
    order = np.lexsort((c, -score, i))
    best = order[np.unique(i[order], return_index=True)[1]]
    stay = score[own]  # by vertex, as i ascends
    go = (score[best] > stay + 10.0**-digits) & (c[best] != comm)
    return np.flatnonzero(go), c[best][go]


def synchronous_louvain(
    src: np.ndarray, dst: np.ndarray, w: np.ndarray, *, kind: str = "flow", two_m: float | None = None, gain: str = "exact", resolution: float = 1.0,
    delta_mode: str = "carried", swap_rule: str = "smaller", lag_hops: int | str = "closure", stale_rounds: int = 3, max_rounds: int = 20, max_levels: int = 20,
    digits: int | None = None,
) -> tuple[np.ndarray, list[np.ndarray], list[tuple]]:
    """The synchronous search of a graph that fits into one task: the same rounds as the distributed one.

    Returns vertex ids, the community of each by level, and the log (see ``louvain.RoundLog``).
    """
    ids, ends = np.unique(np.concatenate([src, dst]), return_inverse=True)
    s, d, w = ends[: len(src)], ends[len(src) :], np.asarray(w, float)
    n, place, names = len(ids), np.arange(len(ids)), np.arange(len(ids))
    digits = tie_digits(len(w)) if digits is None else digits
    if two_m is None:
        two_m = 2 * float(w.sum())
    levels: list[np.ndarray] = []
    log: list[tuple] = []
    if n == 0 or two_m <= 0:
        return ids, [ids.copy()], log
    x, y = vertex_numbers(s, d, w, n, kind)
    last = None
    for level in range(max_levels):
        out = s != d
        key, inverse = np.unique(np.concatenate([s[out] * n + d[out], d[out] * n + s[out]]), return_inverse=True)
        v, u, a = key // n, key % n, np.bincount(inverse, np.tile(w[out], 2), len(key))
        comm = np.arange(n)
        best, best_q, stale = comm, quality(s, d, w, comm, x, y, two_m, resolution), 0
        for number in range(max_rounds):
            who, new = synchronous_moves(v, u, a, comm, x, y, two_m, gain, resolution, digits)
            old = comm[who]
            crossed = np.isin(old * n + new, new * n + old)
            moved, swaps = len(who), int(crossed.sum())
            if moved == 0:
                log.append((level, number, 0, 0, 0, best_q, "settled"))
                break
            kept = ~crossed | (new < old) if swap_rule == "smaller" else ~crossed
            who, old, new = who[kept], old[kept], new[kept]
            leaves = who == old
            owners = dict(zip(old[leaves].tolist(), new[leaves].tolist()))
            ahead = owners if lag_hops == 1 else follow_owners(owners)
            to = np.array([ahead.get(c, c) for c in new.tolist()], np.int64)
            changed = int((to != old).sum())
            comm = comm.copy()
            comm[who] = to
            q = quality(s, d, w, comm, x, y, two_m, resolution)
            if q > best_q + EPS:
                best, best_q, stale = comm, q, 0
            else:
                stale += 1
            stop = "settled" if changed == 0 else "no gain" if stale >= stale_rounds else "round bound" if number + 1 == max_rounds else None
            log.append((level, number, moved, swaps, int((to != new).sum()), q, stop))
            if stop:
                break
        if last is not None and best_q <= last + 1e-9:
            break
        last = best_q
        settled = bool((best == np.arange(n)).all())
        labels, best = np.unique(best, return_inverse=True)
        place, names = best[place], names[labels]
        levels.append(ids[names][place])
        if settled:
            break
        if level + 1 == max_levels:
            log.append((level, None, None, None, None, best_q, "level bound"))
            break
        s, d, n = best[s], best[d], len(labels)
        key, inverse = np.unique(s * n + d, return_inverse=True)
        w, s, d = np.bincount(inverse, w), key // n, key % n
        if delta_mode == "carried":
            x, y = np.bincount(best, x, n), np.bincount(best, y, n)
        else:
            x, y = vertex_numbers(s, d, w, n, kind)
    return ids, levels or [ids.copy()], log
