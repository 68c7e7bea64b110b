"""In-task methods on one component, cluster or small pool, as numpy on numbered records."""

from __future__ import annotations

import heapq

import numpy as np


def mixed(x: np.ndarray) -> np.ndarray:
    """A well-mixed 64-bit hash of whole numbers."""
    with np.errstate(over="ignore"):
        x = np.asarray(x).astype(np.uint64) * np.uint64(0x9E3779B97F4A7C15)
        x = (x ^ (x >> np.uint64(32))) * np.uint64(0xD6E8FEB86659FD93)
        x = (x ^ (x >> np.uint64(32))) * np.uint64(0xD6E8FEB86659FD93)
        return x ^ (x >> np.uint64(32))


def pair_hash(u: np.ndarray, w: np.ndarray, seed: int) -> np.ndarray:
    return mixed(mixed(mixed(np.asarray(u) + 1) ^ (np.asarray(w).astype(np.uint64) + np.uint64(7))) ^ np.uint64(seed))


def components(n: int, a: np.ndarray, b: np.ndarray) -> np.ndarray:
    """Least number reachable from each of n nodes."""
    label = np.arange(n)
    while len(a):
        low = np.minimum(label[a], label[b])
        new = label.copy()
        np.minimum.at(new, a, low)
        np.minimum.at(new, b, low)
        np.minimum.at(new, label[a], low)
        np.minimum.at(new, label[b], low)
        new = new[new]
        if (new == label).all():
            break
        label = new
    return label


def bottleneck(n: int, a: np.ndarray, b: np.ndarray, p: np.ndarray) -> tuple[np.ndarray, np.ndarray]:
    """Matrices of the heaviest positive path and the heaviest winning negative path; a path weighs its weakest edge."""
    q, r = np.round(p, 9), np.round(1 - p, 9)
    pos, neg = np.zeros((n, n)), np.zeros((n, n))
    for at in np.unique(np.concatenate([q, r])):  # from weak to strong, so that the strongest stays
        if at > 0.5:
            label = components(n, a[q >= at], b[q >= at])
            same = label[:, None] == label[None, :]
            pos[same] = at
            met = np.zeros((n, n), bool)
            met[label[a[r >= at]], label[b[r >= at]]] = True
            met |= met.T
            neg[met[label][:, label] & ~same] = at
    return pos, neg


def log_odds(p: np.ndarray) -> np.ndarray:
    q = np.clip(p, 1e-9, 1 - 1e-9)
    return np.round(np.log(q) - np.log1p(-q), 12)


def agglomerate(n: int, a: np.ndarray, b: np.ndarray, odds: np.ndarray, whole: np.ndarray | None = None, bound: tuple[float, float, float] | None = None) -> np.ndarray:
    """Greedy merging of the pair of clusters of greatest summed odds while it is positive; ties by least ids.

    It stops before a pair (-odds, x, y) that does not precede ``bound``, or that has an end whose links are
    not all given (not ``whole``).
    """
    if len(odds) > 50_000 and 20 * np.count_nonzero(odds > 0) <= len(odds):
        return agglomerate_few(n, a, b, odds, whole, bound)
    links: list[dict[int, float]] = [{} for _ in range(n)]
    for x, y, o in zip(a.tolist(), b.tolist(), odds.tolist(), strict=True):
        links[x][y] = links[x].get(y, 0.0) + o
        links[y][x] = links[y].get(x, 0.0) + o
    heap = [(-o, x, y) for x in range(n) for y, o in links[x].items() if x < y and o > 1e-12]
    heapq.heapify(heap)
    label, alive = np.arange(n), [True] * n
    while heap:
        o, x, y = heapq.heappop(heap)
        if not (alive[x] and alive[y]) or links[x].get(y) != -o:
            continue
        if (bound is not None and (o, x, y) >= bound) or (whole is not None and not (whole[x] and whole[y])):
            break
        alive[y] = False
        label[y] = x
        del links[x][y]
        for z, v in links[y].items():
            if z == x:
                continue
            del links[z][y]
            s = round(links[x].get(z, 0.0) + v, 12)
            links[x][z] = links[z][x] = s
            if s > 1e-12:
                heapq.heappush(heap, (-s, min(x, z), max(x, z)))
        links[y] = {}
    while (label != label[label]).any():
        label = label[label]
    return label


def agglomerate_few(n: int, a: np.ndarray, b: np.ndarray, odds: np.ndarray, whole: np.ndarray | None = None, bound: tuple[float, float, float] | None = None) -> np.ndarray:
    """The merges of ``agglomerate`` where few links are positive.

    Sums are kept only for pairs of clusters with a positive link, as no other can be positive; the links of a pair
    that becomes one of these are summed then.
    """
    near: list[dict[int, float]] = [{} for _ in range(n)]
    inner = a != b
    a, b, odds = a[inner], b[inner], odds[inner]
    keys, back = np.unique(np.minimum(a, b).astype(np.int64) * n + np.maximum(a, b), return_inverse=True)
    up = np.zeros(len(keys), bool)
    up[back[odds > 0]] = True
    total = np.bincount(back, odds, len(keys))
    for key, o in zip(keys[up].tolist(), total[up].tolist(), strict=True):
        x, y = divmod(key, n)
        near[x][y] = near[y][x] = o
    ends, others, weights = np.concatenate([keys // max(n, 1), keys % max(n, 1)]), np.concatenate([keys % max(n, 1), keys // max(n, 1)]), np.concatenate([total, total])
    order = np.argsort(ends, kind="stable")
    others, weights = others[order].astype(np.int32), weights[order]
    first = np.searchsorted(ends[order], np.arange(n + 1))
    degree, members = np.diff(first).tolist(), [[x] for x in range(n)]
    label, alive, place = np.arange(n), [True] * n, np.zeros(n, np.int32)

    def links_of(nodes: list[int]) -> np.ndarray:
        if len(nodes) == 1:
            return np.arange(first[nodes[0]], first[nodes[0] + 1])
        at = np.array(nodes)
        size = first[at + 1] - first[at]
        return np.repeat(first[at] - np.cumsum(size) + size, size) + np.arange(size.sum())

    def between(x: int, zs: list[int]) -> list[tuple[int, float, int]]:
        """Each of the clusters zs with the sum and the number of all its links with cluster x, by the side that has fewer links."""
        if degree[x] <= sum(degree[z] for z in zs):
            at = links_of(members[x])
            place[zs] = np.arange(1, len(zs) + 1)
            own = place[label[others[at]]]
            place[zs] = 0
        else:
            at = links_of([m for z in zs for m in members[z]])
            own = np.where(label[others[at]] == x, np.repeat(np.arange(1, len(zs) + 1), [degree[z] for z in zs]), 0)
        own, at = own[own > 0], at[own > 0]
        return list(zip(zs, np.bincount(own, weights[at], len(zs) + 1)[1:].tolist(), np.bincount(own, minlength=len(zs) + 1)[1:].tolist(), strict=True))

    heap = [(-o, x, y) for x in range(n) for y, o in near[x].items() if x < y and o > 1e-12]
    heapq.heapify(heap)
    while heap:
        o, x, y = heapq.heappop(heap)
        if not (alive[x] and alive[y]) or near[x].get(y) != -o:
            continue
        if (bound is not None and (o, x, y) >= bound) or (whole is not None and not (whole[x] and whole[y])):
            break
        del near[x][y], near[y][x]
        mine, its = near[x], near[y]
        more = {z: mine[z] + v for z, v in its.items() if z in mine}
        for own, c in ((its, x), (mine, y)):
            zs = [z for z in own if z not in more]
            if zs:
                more |= {z: own[z] + v for z, v, many in between(c, zs) if many or c == x}
        alive[y] = False
        label[members[y]] = x
        members[x] += members[y]
        degree[x] += degree[y]
        near[y], members[y] = {}, []
        for z in its:
            del near[z][y]
        for z, v in more.items():
            s = round(v, 12)
            if mine.get(z) != s:
                mine[z] = near[z][x] = s
                if s > 1e-12:
                    heapq.heappush(heap, (-s, min(x, z), max(x, z)))
    return label


#: Cells of a matrix that take the memory of a link in ``agglomerate``.
CELLS = 50


def agglomerate_dense(n: int, a: np.ndarray, b: np.ndarray, odds: np.ndarray) -> np.ndarray:
    """The merges of ``agglomerate``, by rows of a matrix; for graphs of at least n * n / CELLS links."""
    m = np.zeros((n, n))
    np.add.at(m, (a, b), odds)
    m += m.T
    np.fill_diagonal(m, -np.inf)
    label, best = np.arange(n), m.argmax(axis=1)  # the first of equals, so the least id
    top = m[label, best]
    while n and top[x := int(top.argmax())] > 1e-12:
        y = int(best[x])  # greater than x, as its row would else be the first of the top
        row = np.round(m[x] + m[y], 12)
        row[x] = row[y] = -np.inf
        m[x] = m[:, x] = row
        m[y] = m[:, y] = -np.inf
        label[y] = x
        best[x], top[x] = row.argmax(), row.max()
        best[y], top[y] = -1, -np.inf
        gain = (row > top) | ((row == top) & (x < best) & (row > -np.inf))
        stale = np.flatnonzero(((best == x) | (best == y)) & ~gain)
        best[gain], top[gain] = x, row[gain]
        rows = m[stale]
        best[stale] = rows.argmax(axis=1)
        top[stale] = rows.max(axis=1)
    while (label != label[label]).any():
        label = label[label]
    return label


def average_merges(n: int, a: np.ndarray, b: np.ndarray, odds: np.ndarray) -> np.ndarray:
    """Greedy merging of the pair of clusters of greatest mean odds while it is positive; ties by least ids."""
    links: list[dict[int, tuple[float, int]]] = [{} for _ in range(n)]
    for x, y, o in zip(a.tolist(), b.tolist(), odds.tolist(), strict=True):
        links[x][y] = links[y][x] = (links[x].get(y, (0.0, 0))[0] + o, links[x].get(y, (0.0, 0))[1] + 1)
    mean = lambda v: round(v[0] / v[1], 12)
    heap = [(-mean(v), x, y) for x in range(n) for y, v in links[x].items() if x < y and v[0] > 1e-12]
    heapq.heapify(heap)
    label = np.arange(n)
    while heap:
        o, x, y = heapq.heappop(heap)
        if y not in links[x] or -mean(links[x][y]) != o:
            continue
        label[label == y] = x
        del links[x][y]
        for z, v in links[y].items():
            if z == x:
                continue
            del links[z][y]
            old = links[x].get(z, (0.0, 0))
            links[x][z] = links[z][x] = new = (round(old[0] + v[0], 12), old[1] + v[1])
            if new[0] > 1e-12:
                heapq.heappush(heap, (-mean(new), min(x, z), max(x, z)))
        links[y] = {}
    return label


def local_moves(n: int, a: np.ndarray, b: np.ndarray, odds: np.ndarray, sweeps: int = 50) -> np.ndarray:
    """From singletons, move records one by one to the neighbouring cluster of greatest summed odds while that helps."""
    near: list[list[tuple[int, float]]] = [[] for _ in range(n)]
    for x, y, o in zip(a.tolist(), b.tolist(), odds.tolist(), strict=True):
        near[x].append((y, o))
        near[y].append((x, o))
    label = list(range(n))
    for _ in range(sweeps):
        moved = False
        for x in range(n):
            pull: dict[int, float] = {}
            for y, o in near[x]:
                pull[label[y]] = pull.get(label[y], 0.0) + o
            own = pull.get(label[x], 0.0)
            best = max(((o, -c) for c, o in pull.items()), default=(0.0, 0))
            if best[0] > max(own, 0.0) + 1e-12:
                label[x], moved = -best[1], True
            elif own < -1e-12:
                label[x], moved = next(c for c in range(n) if c not in label), True
        if not moved:
            break
    out = np.array(label)
    least = {c: int(np.flatnonzero(out == c)[0]) for c in set(label)}
    return np.array([least[c] for c in label])


def partitions(n: int):
    """All partitions of n records as label tuples, first occurrence in order."""

    def grow(prefix: tuple[int, ...], top: int):
        if len(prefix) == n:
            yield prefix
            return
        for c in range(top + 1):
            yield from grow((*prefix, c), max(top, c + 1))

    yield from grow((), 0)


def best_partition(n: int, a: np.ndarray, b: np.ndarray, p: np.ndarray) -> tuple[np.ndarray, float]:
    """Likelihood maximiser by trying all partitions of at most nine records; the earliest of equals."""
    if n > 9:
        raise ValueError("all partitions of more than nine records are too many")
    best, score = None, -1.0
    for labels in partitions(n):
        x = np.array(labels)
        s = float(np.prod(np.where(x[a] == x[b], p, 1 - p)))
        if s > score + 1e-15:
            best, score = x, s
    return best, score


def connect_exact(n: int, a: np.ndarray, b: np.ndarray, p: np.ndarray) -> float:
    """Chance that the present edges connect all n nodes, by the states of each edge in turn."""
    states = {tuple(range(n)): 1.0}
    for x, y, q in zip(a.tolist(), b.tolist(), p.tolist(), strict=True):
        after: dict[tuple[int, ...], float] = {}
        for s, prob in states.items():
            if q < 1:
                after[s] = after.get(s, 0.0) + prob * (1 - q)
            if q > 0:
                lo, hi = sorted((s[x], s[y]))
                t = tuple(lo if c == hi else c for c in s)
                after[t] = after.get(t, 0.0) + prob * q
        states = after
    return sum(prob for s, prob in states.items() if len(set(s)) == 1)


class Sample:
    """Component labels of the nodes in sampled worlds of one cluster."""

    def __init__(self, labels: np.ndarray):
        self.labels = labels  # (nodes, samples)
        self.parts = (labels == np.arange(len(labels))[:, None]).sum(axis=0)
        self.connect = float((self.parts == 1).mean())

    @classmethod
    def draw(cls, ids: np.ndarray, a: np.ndarray, b: np.ndarray, p: np.ndarray, samples: int, seed: int) -> Sample:
        base = pair_hash(ids[a], ids[b], seed)
        labels = np.repeat(np.arange(len(ids))[:, None], samples, axis=1)
        rows = mixed(base[:, None] ^ mixed(np.arange(1, samples + 1))[None, :])
        present = (rows >> np.uint64(11)) * (1.0 / (1 << 53)) < p[:, None]
        order = np.argsort(-p, kind="stable")
        while True:
            before = labels.copy()
            for e in order:
                on = present[e]
                x, y = labels[a[e]], labels[b[e]]
                low = np.minimum(x, y)
                labels[a[e]] = np.where(on, low, x)
                labels[b[e]] = np.where(on, low, y)
            labels = np.minimum(labels, np.take_along_axis(labels, labels, axis=0))
            if (labels == before).all():
                return cls(labels)

    def _second(self) -> np.ndarray:
        """Of the worlds in two parts: which nodes (rows) are not in the first node's part."""
        two = self.labels[:, self.parts == 2]
        return (two != two[:1]).astype(np.float32)

    def connect_with(self) -> np.ndarray:
        """Matrix: the connectivity if the pair (row, column) were surely joined."""
        x = self._second()
        apart = x @ (1 - x).T
        return self.connect + (apart + apart.T) / self.labels.shape[1]

    def connect_pairs(self, i: np.ndarray, j: np.ndarray, piece: int = 4096) -> np.ndarray:
        """The same for the pairs (i, j) alone, so that a large cluster needs no matrix of all its pairs."""
        x = self._second()
        apart = [(x[i[k : k + piece]] != x[j[k : k + piece]]).sum(axis=1) for k in range(0, len(i), piece)]
        return self.connect + (np.concatenate(apart) if apart else np.zeros(0)) / self.labels.shape[1]


def walked(ids: np.ndarray, a: np.ndarray, b: np.ndarray, p: np.ndarray, samples: int, seed: int) -> float:
    """Share of sampled worlds that a walk from the first record reaches whole, drawing only the edges that it meets.

    Draws depend on (pair, world) alone, so this gives what drawing every edge gives; a world is left as soon as
    its walk has reached all records or has nowhere to go.
    """
    base = pair_hash(ids[a], ids[b], seed)
    near: list[list[tuple[int, int]]] = [[] for _ in ids]
    for e, (x, y) in enumerate(zip(a.tolist(), b.tolist(), strict=True)):
        near[x].append((y, e))
        near[y].append((x, e))
    whole = 0
    for world in range(1, samples + 1):
        salt = mixed(np.array([world]))[0]
        seen, todo = {0}, [0]
        while todo and len(seen) < len(ids):
            met = [(y, e) for y, e in near[todo.pop()] if y not in seen]
            if met:
                at = np.array([e for _, e in met])
                on = (mixed(base[at] ^ salt) >> np.uint64(11)) * (1.0 / (1 << 53)) < p[at]
                for (y, _), there in zip(met, on.tolist(), strict=True):
                    if there and y not in seen:
                        seen.add(y)
                        todo.append(y)
        whole += len(seen) == len(ids)
    return whole / samples
