"""Single-task kernels over NumPy arrays: the finish of the distributed loops, and references.

Edges come as vertex arrays ``u``, ``v`` sorted by falling order (first edge heaviest).
"""

from __future__ import annotations

import heapq

import numpy as np
import pyarrow as pa

VECTOR_PHASES = 24


def dense(u: np.ndarray, v: np.ndarray) -> tuple[np.ndarray, np.ndarray, int]:
    """Vertex names as 0..n-1."""
    names, at = np.unique(np.concatenate([u, v]), return_inverse=True)
    return at[: len(u)], at[len(u) :], len(names)


def local_max_phases(u: np.ndarray, v: np.ndarray) -> tuple[np.ndarray, np.ndarray]:
    """Phase in which each edge is matched and in which it is removed (0: never matched).

    Whole-array phases first; a long tail of phases is finished by one scan in falling order:
    an edge is matched if both ends are free, one phase after the last heavier neighbour went.
    """
    a, b, n = dense(u, v)
    live = np.arange(len(a))
    matched, removed = np.zeros(len(a), np.int64), np.zeros(len(a), np.int64)
    best = np.empty(n, np.int64)
    phase = 0
    while len(live) and phase < VECTOR_PHASES:
        phase += 1
        best[a[live]] = best[b[live]] = len(a)
        back = live[::-1]  # the last write to a place is that of the heaviest edge
        best[a[back]] = back
        other = np.full(n, len(a), np.int64) if phase == 1 else other
        other[a[live]] = other[b[live]] = len(a)
        other[b[back]] = back
        top = np.minimum(best, other)
        won = live[(top[a[live]] == live) & (top[b[live]] == live)]
        matched[won] = phase
        covered = np.zeros(n, bool)
        covered[a[won]] = covered[b[won]] = True
        gone = covered[a[live]] | covered[b[live]]
        removed[live[gone]] = phase
        live = live[~gone]
    if len(live):
        taken, latest = np.zeros(n, np.int64), np.full(n, phase, np.int64)
        for e in live.tolist():
            x, y = a[e], b[e]
            if taken[x] == 0 and taken[y] == 0:
                t = max(latest[x], latest[y]) + 1
                matched[e] = removed[e] = taken[x] = taken[y] = t
            else:
                t = min(k for k in (taken[x], taken[y]) if k)
                removed[e] = t
            latest[x], latest[y] = max(latest[x], t), max(latest[y], t)
    return matched, removed


def greedy_scan(u: np.ndarray, v: np.ndarray) -> np.ndarray:
    """Edges taken by one scan in falling order."""
    a, b, n = dense(u, v)
    free, out = bytearray(b"\x01" * n), np.zeros(len(a), bool)
    for e, (x, y) in enumerate(zip(a.tolist(), b.tolist())):
        if free[x] and free[y]:
            free[x] = free[y] = 0
            out[e] = True
    return out


def heavy_edge_scan(u: np.ndarray, v: np.ndarray, rank: dict[int, int]) -> np.ndarray:
    """Vertices in order of rank; each free one takes its heaviest edge to a free neighbour."""
    near: dict[int, list[int]] = {}
    for e, (x, y) in enumerate(zip(u.tolist(), v.tolist())):
        near.setdefault(x, []).append(e)
        near.setdefault(y, []).append(e)
    free, out = set(near), np.zeros(len(u), bool)
    for x in sorted(near, key=rank.__getitem__):
        if x in free:
            for e in near[x]:
                y = int(v[e]) if int(u[e]) == x else int(u[e])
                if y in free:
                    free -= {x, y}
                    out[e] = True
                    break
    return out


def heavy_edge_sweep(first: np.ndarray, other: np.ndarray) -> np.ndarray:
    """``heavy_edge_scan`` of edges that lie in order: by the turn of the end that comes first, each
    end's in falling order. An edge counts in the turn of that end only: if that one stays free, the
    other end was taken by then."""
    a, b, n = dense(first, other)
    free, out = bytearray(b"\x01" * n), np.zeros(len(a), bool)
    for e, (x, y) in enumerate(zip(a.tolist(), b.tolist())):
        if free[x] and free[y]:
            free[x] = free[y] = 0
            out[e] = True
    return out


def pointer_scan(u: np.ndarray, v: np.ndarray) -> np.ndarray:
    """Each vertex points along its sorted list at the first free neighbour; mutual pointers
    match, and those that pointed at a matched vertex move on."""
    a, b, n = dense(u, v)
    order = np.argsort(np.concatenate([a, b]), kind="stable")
    edge = np.concatenate([np.arange(len(a)), np.arange(len(a))])[order]
    starts = np.searchsorted(np.concatenate([a, b])[order], np.arange(n + 1))
    lists = [np.sort(edge[starts[x] : starts[x + 1]]).tolist() for x in range(n)]
    ends = list(zip(a.tolist(), b.tolist()))
    at, free, out = [0] * n, [True] * n, np.zeros(len(a), bool)

    def aim(x: int) -> int:
        own = lists[x]
        while at[x] < len(own):
            y, z = ends[own[at[x]]]
            if free[z if y == x else y]:
                return own[at[x]]
            at[x] += 1
        return -1

    waiting = list(range(n))
    while waiting:
        x = waiting.pop()
        if not free[x] or (e := aim(x)) < 0:
            continue
        y = ends[e][1] if ends[e][0] == x else ends[e][0]
        if aim(y) == e:
            free[x] = free[y] = False
            out[e] = True
            for z in (x, y):
                for f in lists[z]:
                    p, q = ends[f]
                    waiting.append(q if p == z else p)
    return out


def exact_weight(u: np.ndarray, v: np.ndarray, w: np.ndarray) -> tuple[float, list[int]]:
    """Heaviest matching of a graph of up to 22 vertices, by dynamic programming over subsets."""
    a, b, n = dense(u, v)
    if n > 22:
        raise ValueError("too many vertices for the subset method")
    near: list[list[tuple[int, int]]] = [[] for _ in range(n)]
    for e, (x, y) in enumerate(zip(a.tolist(), b.tolist())):
        near[min(x, y)].append((max(x, y), e))
    known: dict[int, tuple[float, tuple]] = {}

    def best(mask: int):
        if mask in known:
            return known[mask]
        x = (mask & -mask).bit_length() - 1 if mask else -1
        if x < 0:
            return 0.0, ()
        rest = mask & ~(1 << x)
        top = best(rest)
        for y, e in near[x]:
            if rest >> y & 1:
                value, edges = best(rest & ~(1 << y))
                if value + w[e] > top[0]:
                    top = (value + w[e], (*edges, e))
        known[mask] = top
        return top

    value, chosen = best((1 << n) - 1)
    return float(value), list(chosen)


def assignment(u: np.ndarray, v: np.ndarray, w: np.ndarray) -> np.ndarray:
    """Positions of the heaviest matching of a bipartite graph whose sides are the values of u and of v."""
    return priced_assignment(u, v, w)[0]


def priced_assignment(u: np.ndarray, v: np.ndarray, w: np.ndarray) -> tuple[np.ndarray, np.ndarray, np.ndarray]:
    """``(positions, vertices, prices)``: the heaviest matching of a bipartite graph and prices that
    prove it. Prices are integers of 0 or more, every edge weighs at most the sum of its two, and
    those of the matching make up its weight.

    Shortest augmenting paths over the edges alone, a vertex of the smaller side at a time; a path
    ends at a free column, or at a row that is left free.
    """
    rows, a = np.unique(u, return_inverse=True)
    cols, b = np.unique(v, return_inverse=True)
    if np.intersect1d(rows, cols).size:
        raise ValueError("the sides overlap")
    if len(rows) > len(cols):
        rows, cols, a, b = cols, rows, b, a
    n = len(rows)
    order = np.lexsort((-w, a))
    starts = np.searchsorted(a[order], np.arange(n + 1)).tolist()
    to, gain, edge = b[order].tolist(), [int(x) for x in w[order]], order.tolist()
    left = [max(gain[starts[r]], 0) if starts[r] < starts[r + 1] else 0 for r in range(n)]
    right, owner, through = [0] * len(cols), [-1] * len(cols), [-1] * len(cols)
    column = [-1] * n
    for first in range(n):
        far, came, done, reached = {}, {}, [], []
        limit, last = left[first], (first, -1)  # the row itself stays free
        queue, row, at = [], first, 0
        while True:
            reached.append((row, at))
            price = left[row] + at
            if price < limit:
                limit, last = price, (row, -1)
            for k in range(starts[row], starts[row + 1]):
                if price - gain[k] >= limit:
                    break  # falling weights: no later edge is nearer than the best end
                c = to[k]
                step = price + right[c] - gain[k]
                if step < limit and step < far.get(c, limit):
                    far[c], came[c] = step, (row, k)
                    heapq.heappush(queue, (step, c))
                    if owner[c] < 0:
                        limit, last = step, (-1, c)
            while queue and queue[0][0] > far[queue[0][1]]:
                heapq.heappop(queue)
            if not queue or queue[0][0] >= limit:
                break
            at, c = heapq.heappop(queue)
            done.append((c, at))
            row = owner[c]
        for r, d in reached:
            left[r] -= max(limit - d, 0)
        for c, d in done:
            right[c] += max(limit - d, 0)
        row, c = last
        if c < 0:  # the row gives its column away
            c, column[row] = column[row], -1
        while c >= 0:
            row, k = came[c]
            before, column[row] = column[row], c
            owner[c], through[c] = row, k
            c = before
    taken = np.array([edge[k] for c, k in enumerate(through) if owner[c] >= 0], np.int64)
    return taken, np.concatenate([rows, cols]), np.array(left + right, np.int64)


def path_optimum(w: list[float], cycle: bool) -> list[int]:
    """Positions of the heaviest set of links of a path (or even cycle) of which no two touch."""

    def along(lo: int, hi: int) -> tuple[float, list[int]]:
        take, skip = [0.0] * (hi - lo + 1), [0.0] * (hi - lo + 1)
        for i in range(lo, hi):
            take[i - lo + 1] = skip[i - lo] + w[i]
            skip[i - lo + 1] = max(take[i - lo], skip[i - lo])
        k, out, on = hi - lo, [], take[-1] > skip[-1]
        total = max(take[-1], skip[-1])
        while k > 0:
            if on:
                out.append(lo + k - 1)
                on = False
            else:
                on = take[k - 1] > skip[k - 1]
            k -= 1
        return total, out

    if not cycle:
        return along(0, len(w))[1]
    return max(along(1, len(w)), along(0, len(w) - 1), key=lambda x: x[0])[1]


def global_paths_scan(u: np.ndarray, v: np.ndarray, w: np.ndarray) -> tuple[np.ndarray, np.ndarray, np.ndarray]:
    """Growth of paths and even cycles in falling order, then their optima.

    Returns per edge: part of the grown graph (-1: not a link), position in it, and whether
    the optimum takes it.
    """
    a, b, n = dense(u, v)
    parent, size, degree = list(range(n)), [0] * n, [0] * n
    near: list[list[int]] = [[] for _ in range(n)]

    def root(x: int) -> int:
        while parent[x] != x:
            parent[x] = parent[parent[x]]
            x = parent[x]
        return x

    ends = list(zip(a.tolist(), b.tolist()))
    for e, (x, y) in enumerate(ends):
        if degree[x] > 1 or degree[y] > 1:
            continue
        rx, ry = root(x), root(y)
        if rx == ry and size[rx] % 2 == 0:
            continue
        parent[ry], size[rx] = rx, size[rx] + (size[ry] if rx != ry else 0) + 1
        degree[x] += 1
        degree[y] += 1
        near[x].append(e)
        near[y].append(e)
    part, place, taken = np.full(len(a), -1), np.zeros(len(a), np.int64), np.zeros(len(a), bool)
    for begin in sorted(range(n), key=lambda x: degree[x] != 1):  # ends of paths first
        if degree[begin] == 0 or part[near[begin][0]] >= 0:
            continue
        walk, x, e = [], begin, near[begin][0]
        while True:
            walk.append(e)
            part[e] = root(begin)
            x = ends[e][1] if ends[e][0] == x else ends[e][0]
            ahead = [f for f in near[x] if part[f] < 0]
            if not ahead:
                break
            e = ahead[0]
        place[walk] = np.arange(len(walk))
        chosen = path_optimum(w[walk].tolist(), degree[begin] == 2)
        taken[[walk[k] for k in chosen]] = True
    return part, place, taken


def one_task(df, compute, out_schema: str, order: list | None = None):
    """All rows through one task: ``compute(table) -> table``. Callers check the size first."""

    def run(batches):
        parts = [b for b in batches if len(b)]
        if parts:
            yield from compute(pa.Table.from_batches(parts)).to_batches()

    single = df.repartition(1)
    return (single.sortWithinPartitions(*order) if order else single).mapInArrow(run, out_schema)
