"""Small exact solvers for graphs that fit one machine: global minimum cut, capped local connectivity, peeling, densest subgraph."""

from __future__ import annotations

import math
from collections import defaultdict, deque
from collections.abc import Iterator
from decimal import ROUND_HALF_UP, Decimal
from heapq import heappop, heappush

import numpy as np
import pyarrow as pa


def stoer_wagner(edges: list[tuple[int, int, float]], vertices: list[int]) -> tuple[float, list[int]]:
    """(weight, one side) of a minimum cut of a connected weighted graph; 0 and a component for others; inf for one vertex."""
    near: dict[int, dict[int, float]] = {v: {} for v in vertices}
    for u, v, w in edges:
        near[u][v] = near[u].get(v, 0) + w
        near[v][u] = near[v].get(u, 0) + w
    groups = {v: [v] for v in vertices}
    best, side = float("inf"), list(vertices)
    while len(near) > 1:
        start = min(near)
        weight, order, left = {v: 0.0 for v in near}, [], set(near)
        at = start
        while True:
            order.append(at)
            left.discard(at)
            if not left:
                break
            for y, w in near[at].items():
                if y in left:
                    weight[y] += w
            at = max(left, key=lambda v: (weight[v], -v))
        last, before = order[-1], order[-2]
        if weight[last] < best:
            best, side = weight[last], sorted(groups[last])
        groups[before] += groups.pop(last)
        for y, w in near.pop(last).items():
            del near[y][last]
            if y != before:
                near[before][y] = near[before].get(y, 0) + w
                near[y][before] = near[before][y]
    return best, side


def max_flow(near: dict[int, dict[int, float]], s: int, t: int, cap: float = float("inf")) -> float:
    """Flow from s to t in an undirected graph by shortest augmenting paths, no further than cap."""
    left = {v: dict(d) for v, d in near.items()}
    total = 0.0
    while total < cap:
        back, q = {s: None}, deque([s])
        while q and t not in back:
            x = q.popleft()
            for y, c in left[x].items():
                if c > 1e-12 and y not in back:
                    back[y] = x
                    q.append(y)
        if t not in back:
            break
        path, y = [], t
        while back[y] is not None:
            path.append((back[y], y))
            y = back[y]
        f = min(cap - total, min(left[a][b] for a, b in path))
        for a, b in path:
            left[a][b] -= f
            left[b][a] += f
        total += f
    return total


def adjacency(edges: list[tuple[int, int, float]]) -> dict[int, dict[int, float]]:
    near: dict[int, dict[int, float]] = defaultdict(dict)
    for u, v, w in edges:
        near[u][v] = near[u].get(v, 0) + w
        near[v][u] = near[u][v]
    return near


def peel(edges: list[tuple[int, int]]) -> tuple[float, list[int]]:
    """Remove a vertex of least degree again and again; the densest stage, within a factor 2 of the densest subgraph."""
    near = defaultdict(set)
    for u, v in edges:
        near[u].add(v)
        near[v].add(u)
    m, order = sum(map(len, near.values())) // 2, []
    buckets = defaultdict(set)
    for v, d in near.items():
        buckets[len(d)].add(v)
    best, cut, low = (m / len(near) if near else 0.0), 0, 0
    left = len(near)
    live = set(near)
    while left > 1:
        low = next(d for d in range(max(0, low - 1), len(live)) if buckets.get(d))
        v = min(buckets[low])
        buckets[low].discard(v)
        live.discard(v)
        order.append(v)
        for y in near[v]:
            if y in live:
                buckets[len(near[y])].discard(y)
                near[y].discard(v)
                buckets[len(near[y])].add(y)
        m -= low
        left -= 1
        if m / left > best:
            best, cut = m / left, len(order)
    return best, sorted(set(near) - set(order[:cut]))


def least_labels(u: np.ndarray, v: np.ndarray) -> tuple[np.ndarray, np.ndarray]:
    """(vertices, the least vertex of each one's component): roots hook to the least root around them, until no edge joins two."""
    ids, at = np.unique(np.concatenate([u, v]), return_inverse=True)
    a, b, up = at[: len(u)], at[len(u) :], np.arange(len(ids))
    while True:
        a, b = up[a], up[b]
        apart = a != b
        if not apart.any():
            return ids, ids[up]
        a, b = a[apart], b[apart]
        np.minimum.at(up, np.maximum(a, b), np.minimum(a, b))
        while (far := up[up]).tobytes() != up.tobytes():
            up = far


class Stars:
    """Edges in batches to stars with the same components: each vertex with the least of its component, of at most room edges at a time. A vertex that only has a loop keeps it."""

    def __init__(self, room: int = 1_000_000):
        self.room = room

    def __call__(self, batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        held, n = [], 0
        for batch in batches:
            held.append((batch["u"].to_numpy(), batch["v"].to_numpy()))
            n += batch.num_rows
            if n >= self.room:
                held = [self.of(held)]
                n = len(held[0][0])
                if n > self.room // 2:  # too many vertices to hold on to
                    yield self.batch(held[0])
                    held, n = [], 0
        if n:
            yield self.batch(self.of(held))

    @staticmethod
    def of(held: list[tuple[np.ndarray, np.ndarray]]) -> tuple[np.ndarray, np.ndarray]:
        ids, label = least_labels(*(np.concatenate(c) for c in zip(*held)))
        if not len(ids):
            return ids, label
        at = np.searchsorted(ids, label)
        keep = (ids != label) | (np.bincount(at, minlength=len(ids))[at] == 1)
        return ids[keep], label[keep]

    @staticmethod
    def batch(stars: tuple[np.ndarray, np.ndarray]) -> pa.RecordBatch:
        return pa.RecordBatch.from_arrays([pa.array(c, pa.int64()) for c in stars], ["u", "v"])


NEAR = 1e-9  # far beyond the rounding of a cosine's sums


def ranked_ends(u: np.ndarray, v: np.ndarray) -> tuple[np.ndarray, np.ndarray, np.ndarray]:
    """(vertices in order, the ends as places among them); by a table of flags where the numbers lie close, which needs no sort."""
    least, most = (int(min(u.min(), v.min())), int(max(u.max(), v.max()))) if len(u) else (0, -1)
    if most - least >= 16 * len(u) + 1000:
        ids, at = np.unique(np.concatenate([u, v]), return_inverse=True)
        return ids, at[: len(u)], at[len(u) :]
    seen = np.zeros(most - least + 1, dtype=bool)
    seen[u - least] = True
    seen[v - least] = True
    place = np.cumsum(seen) - 1
    return np.flatnonzero(seen) + least, place[u - least], place[v - least]


def peel_arrays(u: np.ndarray, v: np.ndarray) -> tuple[float, list[int]]:
    """peel() over two arrays of ends, in the same order of removal: arrays of some 80 bytes an edge at their most, not sets of neighbours.

    The heap holds the vertices up to a degree, the bound, which grows by halves each time that none is left below it;
    a vertex of high degree is lowered many times, and enters the heap only once it is below the bound.
    """
    ids, a, b = ranked_ends(u, v)
    n = len(ids)
    if not n:
        return 0.0, []
    pairs = np.minimum(a, b) * n + np.maximum(a, b)
    del a, b
    pairs.sort()
    pairs = pairs[np.append(True, pairs[1:] != pairs[:-1])]
    m = len(pairs)
    both = np.concatenate([pairs, pairs % n * n + pairs // n])
    del pairs
    both.sort()
    near, counts = (both % n).astype(np.int32), np.bincount(both // n, minlength=n)
    del both
    start, deg = np.concatenate([[0], np.cumsum(counts)]).tolist(), counts.tolist()
    heap, bound = [], -1
    left, live, order = n, bytearray(b"\1") * n, []
    best, cut = m / n, 0
    while left > 1:
        if not heap:  # whatever is left is above the bound
            degrees, alive = np.array(deg), np.frombuffer(live, dtype=bool)
            bound = int(degrees[alive].min()) * 3 // 2
            at = np.flatnonzero(alive & (degrees <= bound))
            heap = np.sort(degrees[at] * n + at).tolist()
        low, x = divmod(heappop(heap), n)
        if not live[x] or deg[x] != low:
            continue  # removed, or lowered since
        live[x] = 0
        order.append(x)
        for y in near[start[x] : start[x + 1]].tolist():
            if live[y]:
                deg[y] = d = deg[y] - 1
                if d <= bound:
                    heappush(heap, d * n + y)
        m -= low
        left -= 1
        if m / left > best:
            best, cut = m / left, len(order)
    keep = np.ones(n, dtype=bool)
    keep[order[:cut]] = False
    return best, ids[keep].tolist()


def peel_batch_arrays(u: np.ndarray, v: np.ndarray, delta: float = 0.1) -> tuple[float, list[int]]:
    """peel_batch() over two arrays of ends, each edge once."""
    ids, at = np.unique(np.concatenate([u, v]), return_inverse=True)
    a, b = at[: len(u)], at[len(u) :]
    best, kept = 0.0, []
    while len(a):
        deg = np.bincount(a, minlength=len(ids)) + np.bincount(b, minlength=len(ids))
        density = len(a) / int(np.count_nonzero(deg))
        if density > best:
            best, kept = density, ids[deg > 0].tolist()
        high = deg > 2 * (1 + delta) * density
        live = high[a] & high[b]
        a, b = a[live], b[live]
    return best, kept


def peel_batch(edges: list[tuple[int, int]], delta: float = 0.1) -> tuple[float, list[int]]:
    """Remove all vertices of degree below (1 + delta) times twice the density, round after round: within 2 (1 + delta)."""
    live, best, kept = set(edges), 0.0, []
    while live:
        deg = defaultdict(int)
        for u, v in live:
            deg[u] += 1
            deg[v] += 1
        density = len(live) / len(deg)
        if density > best:
            best, kept = density, sorted(deg)
        low = {v for v, d in deg.items() if d <= 2 * (1 + delta) * density}
        live = {(u, v) for u, v in live if u not in low and v not in low}
    return best, kept


def kruskal(edges: list[tuple[int, int, float]]) -> float:
    up: dict[int, int] = {}

    def root(x: int) -> int:
        while up.get(x, x) != x:
            up[x] = up.get(up[x], up[x])
            x = up[x]
        return x

    total = 0.0
    for u, v, w in sorted(edges, key=lambda e: (e[2], e[0], e[1])):
        a, b = root(u), root(v)
        if a != b:
            up[a] = b
            total += w
    return total


def cosine_pairs(ia: np.ndarray, ib: np.ndarray, x: np.ndarray, y: np.ndarray, least: float, same: bool) -> pa.RecordBatch:
    """(a, b), a < b: ids of rows of x and y whose cosine, rounded to six digits, is least or more; vectors of length zero have none. same: x is y, and every pair counts once.

    The product of the blocks decides but for its rounding; near the bound a pair is summed term by term.
    """
    nx, ny = np.sqrt(np.einsum("ij,ij->i", x, x)), np.sqrt(np.einsum("ij,ij->i", y, y))
    with np.errstate(divide="ignore", invalid="ignore"):
        c = (x @ y.T) / np.outer(nx, ny)
    i, j = np.nonzero(c >= least - 5e-7 - NEAR)
    keep = (ia[i] < ib[j]) if same else (ia[i] != ib[j])
    i, j = i[keep], j[keep]
    for k in np.flatnonzero(c[i, j] < least - 5e-7 + NEAR).tolist():
        p, q = x[i[k]].tolist(), y[j[k]].tolist()
        dot = lambda s, t: sum((f * g for f, g in zip(s, t)), 0.0)
        cos = dot(p, q) / (math.sqrt(dot(p, p)) * math.sqrt(dot(q, q)))
        if Decimal(repr(cos)).quantize(Decimal("1e-6"), ROUND_HALF_UP) < Decimal(repr(least)):
            i[k] = -1
    i, j = i[i >= 0], j[i >= 0]
    return pa.RecordBatch.from_arrays([pa.array(np.minimum(ia[i], ib[j])), pa.array(np.maximum(ia[i], ib[j]))], ["a", "b"])
