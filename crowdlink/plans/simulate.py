"""Question loops on one small pool, as a whole run in one task; runs of many settings go side by side.

A pool is every pair that may be asked, with the weight that its votes will show. All methods share the
initial pairs, the votes, the loop and the measures; they differ in clustering, weights and choice.
"""

from __future__ import annotations

import itertools
import time
from functools import cached_property

import numpy as np
import pandas as pd

from crowdlink.operators import kernels
from crowdlink.operators.kernels import agglomerate, components, log_odds, mixed, pair_hash

METHODS = ("reliability", "reliability_size", "tc", "dense", "bdense", "minmax", "pivot", "random")


def pair_counts(label: np.ndarray) -> int:
    n = np.unique(label, return_counts=True)[1]
    return int((n * (n - 1) // 2).sum())


class Grown:
    """Columns that get more rows."""

    def __init__(self, *kinds: type):
        self.size, self.room = 0, [np.empty(1024, k) for k in kinds]

    def add(self, *columns: np.ndarray) -> None:
        end = self.size + len(columns[0])
        for k, c in enumerate(columns):
            if end > len(self.room[k]):
                self.room[k] = np.concatenate([self.room[k][: self.size], np.empty(end, self.room[k].dtype)])
            self.room[k][self.size : end] = c
        self.size = end

    def columns(self) -> list[np.ndarray]:
        return [x[: self.size] for x in self.room]


class Growing:
    """The clusters of ``agglomerate`` while links are added; only what new links can change is merged again.

    Between two blocks the positive links sum up to ``weak`` at most, the least positive odds of all. So as long as
    greater sums are left, greedy merges inside blocks alone, in each as if there were no others; a block without
    new links keeps these clusters. The rest of the merges is made on the clusters so far, where few sums are positive.
    """

    def __init__(self, n: int, odds: np.ndarray):
        self.n, self.links, self.good = n, Grown(np.int32, np.int32, float), Grown(np.int32, np.int32)
        positive = np.unique(odds[odds > 1e-12])
        self.weak = float(positive[0]) if len(positive) > 1 else 0.0
        self.block, self.members = np.arange(n, dtype=np.int32), {x: [x] for x in range(n)}
        self.thin: list[dict[int, int]] = [{} for _ in range(n)]  # weak links between blocks
        self.label = np.arange(n)

    def _join(self, x: int, y: int) -> None:
        todo = [(x, y)]
        while todo:
            x, y = (int(self.block[z]) for z in todo.pop())
            if x == y:
                continue
            if len(self.members[x]) < len(self.members[y]):
                x, y = y, x
            moved = self.members.pop(y)
            self.members[x] += moved
            self.block[moved] = x
            self.thin[x].pop(y, None)
            for z, k in self.thin[y].items():
                if z != x:
                    del self.thin[z][y]
                    k = self.thin[x][z] = self.thin[z][x] = self.thin[x].get(z, 0) + k
                    if k > 1:
                        todo.append((x, z))
            self.thin[y] = {}

    def add(self, a: np.ndarray, b: np.ndarray, odds: np.ndarray) -> np.ndarray:
        """Labels with these links, each of two records that had none."""
        self.links.add(a, b, odds)
        up = odds > 1e-12
        self.good.add(a[up], b[up])
        for x, y, o in zip(a[up].tolist(), b[up].tolist(), odds[up].tolist(), strict=True):
            x, y = (int(self.block[z]) for z in (x, y))
            if x != y:
                k = self.thin[x].get(y, 0) + 1
                if o > self.weak or k > 1:
                    self._join(x, y)
                else:
                    self.thin[x][y] = self.thin[y][x] = k
        inner = self.block[a] == self.block[b]
        touched = np.zeros(self.n, bool)
        touched[self.block[a[inner]]] = True
        p, q, o = self.links.columns()
        if touched.any():
            own = self.block[p]
            at = np.flatnonzero((own == self.block[q]) & touched[own])
            nodes = np.flatnonzero(touched[self.block])
            place = np.empty(self.n, np.int64)
            place[nodes] = np.arange(len(nodes))
            bound = (-self.weak, -1, -1) if self.weak else None
            self.label[nodes] = nodes[agglomerate(len(nodes), place[p[at]], place[q[at]], o[at], bound=bound)]
        return self._rest() if self.weak else self.label.copy()

    def _rest(self) -> np.ndarray:
        label, (p, q, o) = self.label, self.links.columns()
        x, y = (label[z] for z in self.good.columns())
        x, y = x[x != y], y[x != y]
        if not len(x):
            return label.copy()

        def sums(mark: np.ndarray, group: np.ndarray | None) -> tuple[np.ndarray, np.ndarray]:
            """Keys and summed odds of the pairs of marked clusters, in one group where groups are given."""
            own = mark[label]
            at = np.flatnonzero(own[p] & own[q])
            i, j = label[p[at]], label[q[at]]
            keep = (i != j) if group is None else (i != j) & (group[i] == group[j])
            keys, back = np.unique(np.minimum(i, j)[keep] * self.n + np.maximum(i, j)[keep], return_inverse=True)
            return keys, np.round(np.bincount(back, o[at[keep]], len(keys)), 12)

        mark = np.zeros(self.n, bool)
        mark[x] = mark[y] = True
        keys, total = sums(mark, None)
        some = keys[total > 1e-12]
        if not len(some):
            return label.copy()
        group = components(self.n, some // self.n, some % self.n)
        mark[:] = False
        mark[some // self.n] = mark[some % self.n] = True
        keys, total = sums(mark, group)
        ids = np.flatnonzero(mark)
        found = np.arange(self.n)
        found[ids] = ids[agglomerate(len(ids), np.searchsorted(ids, keys // self.n), np.searchsorted(ids, keys % self.n), total)]
        return found[label]


def f1_of(label: np.ndarray, entity: np.ndarray) -> tuple[float, float, float]:
    both = pair_counts(label.astype(np.int64) * (int(entity.max()) + 1) + entity)
    reported, true = pair_counts(label), pair_counts(entity)
    p, r = both / reported if reported else 0.0, both / true if true else 0.0
    return p, r, 2 * p * r / (p + r) if p + r else 0.0


class Pool:
    """Pairs by record number, what the crowd says of each, and which have been asked."""

    def __init__(self, n: int, u: np.ndarray, w: np.ndarray, ratio: np.ndarray, majority: np.ndarray, seed: int):
        self.n, self.u, self.w, self.ratio, self.majority, self.seed = n, u, w, ratio, majority, seed
        self.asked = np.zeros(len(u), bool)
        self.hash = pair_hash(u, w, seed)

    @cached_property
    def order(self) -> np.ndarray:
        return np.argsort(self.hash, kind="stable").astype(np.int32)

    @cached_property
    def rank(self) -> np.ndarray:
        """Places of the pairs in ``order``."""
        out = np.empty(len(self.order), np.int32)
        out[self.order] = np.arange(len(out), dtype=np.int32)
        return out

    @cached_property
    def _near(self) -> tuple[np.ndarray, ...]:
        by_u, by_w = (np.argsort(x, kind="stable").astype(np.int32) for x in (self.u, self.w))
        return by_u, np.searchsorted(self.u[by_u], np.arange(self.n + 1)), by_w, np.searchsorted(self.w[by_w], np.arange(self.n + 1))

    def pairs_at(self, mark: np.ndarray) -> np.ndarray:
        """Numbers of the pairs with a marked record, ascending."""
        nodes = np.flatnonzero(mark)
        if 4 * len(nodes) > self.n:
            return np.flatnonzero(mark[self.u] | mark[self.w])
        by_u, u_at, by_w, w_at = self._near
        out = []
        for rows, at in ((by_u, u_at), (by_w, w_at)):
            size = at[nodes + 1] - at[nodes]
            out.append(rows[np.repeat(at[nodes] - np.cumsum(size) + size, size) + np.arange(size.sum())])
        return np.unique(np.concatenate(out))

    def edges(self, weight: np.ndarray) -> tuple[np.ndarray, np.ndarray, np.ndarray]:
        a = self.asked
        return self.u[a], self.w[a], weight[a]


class Greedy:
    """Greedy clustering of the asked pairs by ``weight``; later calls take the fresh pairs alone."""

    def __init__(self, pool: Pool, weight: np.ndarray):
        self.pool, self.weight, self.growing = pool, weight, None
        self.waiting: list[np.ndarray] = []

    def wait(self, fresh: np.ndarray) -> None:
        self.waiting.append(fresh)

    def label(self, fresh: np.ndarray | None) -> np.ndarray:
        p = self.pool
        if self.growing is None or fresh is None:
            values = np.unique(self.weight)
            self.growing, fresh = Growing(p.n, log_odds(values)), np.flatnonzero(p.asked)
        else:
            fresh = np.concatenate([*self.waiting, fresh])
        self.waiting = []
        return self.growing.add(p.u[fresh], p.w[fresh], log_odds(self.weight[fresh]))


def unit_keys(label: np.ndarray, a: np.ndarray, b: np.ndarray) -> np.ndarray:
    x, y = label[a].astype(np.int64), label[b].astype(np.int64)
    return np.minimum(x, y) * len(label) + np.maximum(x, y)


def lesser(keys: np.ndarray, size: np.ndarray) -> np.ndarray:
    """The smaller cluster of each pair of clusters."""
    x, y = keys // len(size), keys % len(size)
    return np.where(size[x] <= size[y], x, y)


class Reliability:
    """Greatest best-case gain; scores inside clusters are kept until the cluster or its answers change.

    What holds for pairs of clusters is kept too, and taken anew only for clusters that changed and pairs of clusters
    that got an answer: the sum of the logs of ``reliability``, and which pairs gain as much as a pair of clusters can.
    """

    def __init__(self, pool: Pool, samples: int, eps: float = 1e-9, tie: str = "hash"):
        self.pool, self.samples, self.eps, self.tie, self.kept = pool, samples, eps, tie, {}
        self.greedy = Greedy(pool, pool.ratio)

    def cluster(self, label: np.ndarray | None, fresh: np.ndarray | None) -> tuple[np.ndarray, bool]:
        p = self.pool
        if label is None or fresh is None:
            self.links, self.fresh, self.old = Grown(np.int32, np.int32, np.int32), [np.flatnonzero(p.asked)], None
            return self.greedy.label(None), True
        self.fresh.append(fresh)
        if len(fresh):
            inside = label[p.u[fresh]] == label[p.w[fresh]]
            if (np.where(inside, p.ratio[fresh], 1 - p.ratio[fresh]) > 0.5).all():
                self.greedy.wait(fresh)
                return label, False
        return self.greedy.label(fresh), True

    def _units(self, label: np.ndarray, mark: np.ndarray, keys: np.ndarray) -> tuple[float, int, np.ndarray]:
        """Of the pairs of clusters with answers, one cluster marked or the key given: sum of logs, number, and keys of those that gain less than all."""
        p, (a, b, c) = self.pool, self.links.columns()
        ends = np.zeros(p.n, bool)
        ends[keys // p.n] = ends[keys % p.n] = True
        x, y = label[a], label[b]
        at = np.flatnonzero((x != y) & (mark[x] | mark[y] | (ends[x] & ends[y])))
        x, y, c = x[at], y[at], c[at]
        unit = np.minimum(x, y) * p.n + np.maximum(x, y)
        keep = mark[x] | mark[y] | np.isin(unit, keys)
        known, back = np.unique(unit[keep], return_inverse=True)
        ratio = p.ratio[c[keep]]
        logs = np.bincount(back, np.log(np.maximum(ratio, 1e-300)), len(known))
        return float(np.log10(np.maximum(-np.expm1(logs), self.eps)).sum()), len(known), known[-np.expm1(logs) > self.eps]

    def _follow(self, label: np.ndarray) -> None:
        """Bring what is kept up to these labels and the answers since."""
        p = self.pool
        if self.old is not None and not self.fresh and (label is self.old or (label == self.old).all()):
            return
        fresh = np.concatenate([*self.fresh, np.empty(0, np.int64)]).astype(np.int64)
        self.fresh = []
        mark = np.zeros(p.n, bool)
        if self.old is None:
            mark[:] = True
            self.logs, self.known, self.inner = 0.0, 0, np.zeros(p.n)
            self.most = np.zeros(len(p.u), np.int64 if self.tie == "size" else bool)  # by rank: size product or whether it is open
            was = mark
        else:
            moved = np.flatnonzero(label != self.old)
            mark[self.old[moved]] = mark[label[moved]] = True
            was = mark[self.old]
        x, y = label[p.u[fresh]], label[p.w[fresh]]
        keys = np.unique((np.minimum(x, y).astype(np.int64) * p.n + np.maximum(x, y))[x != y])
        if self.old is not None:
            # a pair of clusters with no marked one has the same key before and after
            logs, known, _ = self._units(self.old, mark, keys[~(mark[keys // p.n] | mark[keys % p.n])])
            self.logs, self.known = self.logs - logs, self.known - known
        self.links.add(p.u[fresh], p.w[fresh], fresh)
        logs, known, less = self._units(label, mark, keys)
        self.logs, self.known = self.logs + logs, self.known + known
        # pairs of clusters: the least free pair of each that gains most
        size = np.bincount(label, minlength=p.n)
        ends = np.zeros(p.n, bool)
        ends[lesser(keys, size)] = True
        some = p.pairs_at(was | mark[label] | ends[label])
        x, y = label[p.u[some]].astype(np.int64), label[p.w[some]]
        unit = np.minimum(x, y) * p.n + np.maximum(x, y)
        mine = was[p.u[some]] | was[p.w[some]] | mark[x] | mark[y] | np.isin(unit, keys)
        some, unit, x, y = some[mine], unit[mine], x[mine], y[mine]
        self.most[p.rank[some]] = 0
        free = np.flatnonzero(~p.asked[some] & (x != y) & ~np.isin(unit, less))
        free = free[np.unique(unit[free], return_index=True)[1]]
        self.most[p.rank[some[free]]] = size[x[free]] * size[y[free]] if self.tie == "size" else True
        # clusters: their connectivity
        again = mark.copy()
        inside = label[p.u[fresh]] == label[p.w[fresh]]
        again[label[p.u[fresh[inside]]]] = True
        self.inner[again] = 0
        self.split = {c for c in getattr(self, "split", ()) if not again[c]} if self.old is not None else set()
        a, b, c = self.links.columns()
        own = label[a]
        c = np.sort(c[(own == label[b]) & again[own]])
        c = c[np.argsort(label[p.u[c]], kind="stable")]
        ids = np.flatnonzero(again & (size > 1))
        cuts = np.searchsorted(label[p.u[c]], ids), np.searchsorted(label[p.u[c]], ids, side="right")
        for cid, i, j in zip(ids.tolist(), *(k.tolist() for k in cuts), strict=True):
            connect = self._sample(label, cid, c[i:j]).connect
            self.inner[cid] = np.log10(max(connect, self.eps))
            if connect <= self.eps:
                self.split.add(cid)
        self.old = label

    def choose(self, label: np.ndarray, count: int) -> np.ndarray:
        """The best pairs; at first pairs of clusters that gain as much as any pair can, which need no look at the others."""
        self._follow(label)
        p, most = self.pool, self.most
        if self.tie == "size":
            top = int(most.max(initial=0))
            while top and np.count_nonzero(most >= top) < count:
                top //= 2
            pairs = np.flatnonzero(most >= max(top, 1))
            pairs = pairs[np.argsort(-most[pairs], kind="stable")[:count]]
        else:
            pairs, end = np.empty(0, np.int64), 4096
            while len(pairs) < count and end < 2 * len(most) + 4096:
                pairs, end = np.flatnonzero(most[:end])[:count], 2 * end
        if len(pairs) < count:
            return self._choose(label, count)
        best_i, limit = [p.order[pairs].astype(np.int64)], -np.log10(self.eps)
        best_g = [np.full(count, limit)]
        if self.split:  # clusters that no sampled world connects
            mark = np.zeros(p.n, bool)
            mark[list(self.split)] = True
            some = p.pairs_at(mark[label])
            some = some[label[p.u[some]] == label[p.w[some]]]
            for cid in sorted(self.split):
                group = some[label[p.u[some]] == cid]
                open_ = group[~p.asked[group]]
                if len(open_):
                    best_i.append(open_)
                    best_g.append(self._inside(label, cid, group[p.asked[group]], open_, limit))
        gains, pairs = np.concatenate(best_g), np.concatenate(best_i)
        return pairs[np.lexsort((p.hash[pairs], self._ties(label, pairs), -np.round(gains, 9)))[:count]]

    def _ties(self, label: np.ndarray, x: np.ndarray) -> np.ndarray:
        if self.tie != "size":
            return np.zeros(len(x))
        size = np.bincount(label, minlength=self.pool.n)
        return -(size[label[self.pool.u[x]]] * size[label[self.pool.w[x]]])

    def _choose(self, label: np.ndarray, count: int) -> np.ndarray:
        p, limit = self.pool, -np.log10(self.eps)
        inside = label[p.u] == label[p.w]
        keys = unit_keys(label, p.u, p.w)
        known, back = np.unique(keys, return_inverse=True)
        cross = p.asked & ~inside
        logs = np.bincount(back[cross], np.log(np.maximum(p.ratio[cross], 1e-300)), len(known))
        edges = np.bincount(back[cross], minlength=len(known))
        sure = np.bincount(back[cross & (p.ratio <= 0)], minlength=len(known)) > 0
        disc = np.where(sure, 1.0, -np.expm1(logs))
        prio = np.where(edges > 0, -np.log10(np.maximum(disc, self.eps)), limit)
        free = np.flatnonzero(~p.asked & ~inside)
        free = free[np.unique(back[free], return_index=True)[1]]  # pool order is (u, w): the least pair of each unit
        gains, pairs = prio[back[free]], free
        if len(gains) > count:
            order = np.lexsort((p.hash[pairs], self._ties(label, pairs), -np.round(gains, 9)))[:count]
            gains, pairs = gains[order], pairs[order]
        floor = gains.min() if len(gains) >= count else -np.inf
        inner = np.flatnonzero(inside)
        if (~p.asked[inner]).any():
            order = np.argsort(label[p.u[inner]], kind="stable")
            inner = inner[order]
            cuts = np.flatnonzero(np.diff(label[p.u[inner]])) + 1
            best_g, best_i = [gains], [pairs]
            for group in np.split(inner, cuts):
                asked, open_ = group[p.asked[group]], group[~p.asked[group]]
                if not len(open_):
                    continue
                g = self._inside(label, int(label[p.u[group[0]]]), asked, open_, floor)
                if g is not None:
                    best_g.append(g)
                    best_i.append(open_)
            gains, pairs = np.concatenate(best_g), np.concatenate(best_i)
        return pairs[np.lexsort((p.hash[pairs], self._ties(label, pairs), -np.round(gains, 9)))[:count]]

    def reliability(self, label: np.ndarray) -> float:
        """Base-10 logs of all clusters and pairs of clusters; a cluster's worlds are those that its questions use."""
        self._follow(label)
        c = len(np.unique(label))
        return float(self.inner.sum()) + self.logs + (c * (c - 1) // 2 - self.known) * float(np.log10(self.eps))

    def _sample(self, label: np.ndarray, cid: int, asked: np.ndarray) -> kernels.Sample:
        p = self.pool
        nodes = np.flatnonzero(label == cid)
        mark = (len(nodes), int(nodes.sum()), len(asked))
        kept = self.kept.get(cid)
        if kept is None or kept[0] != mark:
            a, b = np.searchsorted(nodes, p.u[asked]), np.searchsorted(nodes, p.w[asked])
            kept = self.kept[cid] = (mark, kernels.Sample.draw(nodes, a, b, p.ratio[asked], self.samples, p.seed))
        return kept[1]

    def _inside(self, label: np.ndarray, cid: int, asked: np.ndarray, open_: np.ndarray, floor: float) -> np.ndarray | None:
        p, nodes = self.pool, np.flatnonzero(label == cid)
        s = self._sample(label, cid, asked)
        if -np.log10(max(s.connect, self.eps)) < floor:  # even a sure edge could not reach the chosen ones
            return None
        a, b = np.searchsorted(nodes, p.u[open_]), np.searchsorted(nodes, p.w[open_])
        return np.log10(np.maximum(s.connect_with()[a, b], self.eps)) - np.log10(max(s.connect, self.eps))


class Transitive:
    """Majority answers, transitive closure, random pairs that closure leaves open.

    Clusters only grow, so a pair that closure or a refusal has decided stays decided: pairs are passed once, in hash order.
    """

    def __init__(self, pool: Pool):
        self.pool, self.at = pool, 0
        self.refused = np.zeros((0, 0), np.uint8)  # bits: whether clusters (row, column) were told apart

    def _refuse(self, x: np.ndarray, y: np.ndarray) -> None:
        for i, j in ((x, y), (y, x)):
            np.bitwise_or.at(self.refused, (i, j >> 3), np.left_shift(1, j & 7).astype(np.uint8))

    def cluster(self, label, fresh):
        p = self.pool
        if label is None or fresh is None:
            fresh = np.flatnonzero(p.asked)
            yes = fresh[p.majority[fresh] > 0.5]
            label, self.at = components(p.n, p.u[yes], p.w[yes]), 0
            self.refused = np.zeros((p.n, (p.n + 7) // 8), np.uint8)
        else:
            label = label.copy()
            yes = fresh[p.majority[fresh] > 0.5]
            for i, j in zip(p.u[yes].tolist(), p.w[yes].tolist(), strict=True):
                x, y = sorted((int(label[i]), int(label[j])))
                if x != y:
                    label[label == y] = x
                    self.refused[x] |= self.refused[y]
                    told = (self.refused[:, y >> 3] >> np.uint8(y & 7)) & np.uint8(1)
                    self.refused[:, x >> 3] |= told << np.uint8(x & 7)
        no = fresh[p.majority[fresh] <= 0.5]
        self._refuse(label[p.u[no]], label[p.w[no]])
        return label, True

    def choose(self, label: np.ndarray, count: int) -> np.ndarray:
        p, found, got = self.pool, [], 0
        while got < count and self.at < len(p.order):
            some = p.order[self.at : self.at + 8 * count]
            x, y = label[p.u[some]], label[p.w[some]]
            told = (self.refused[x, y >> 3] >> (y & 7).astype(np.uint8)) & 1
            free = np.flatnonzero(~p.asked[some] & (x != y) & (told == 0))[: count - got]
            self.at += int(free[-1]) + 1 if got + len(free) == count else len(some)
            found.append(some[free])
            got += len(free)
        return np.concatenate([p.order[:0], *found])


class Random:
    """A control: random unasked pairs, clustered as the reliability-guided method does."""

    def __init__(self, pool: Pool):
        self.pool, self.at, self.greedy = pool, 0, Greedy(pool, pool.ratio)

    def cluster(self, label, fresh):
        return self.greedy.label(None if label is None else fresh), True

    def choose(self, label: np.ndarray, count: int) -> np.ndarray:
        p, found, got = self.pool, [], 0
        while got < count and self.at < len(p.order):
            some = p.order[self.at : self.at + count - got]
            self.at += len(some)
            found.append(some[~p.asked[some]])
            got += len(found[-1])
        return np.concatenate([p.order[:0], *found])


class Density:
    """[R] Majority answers of one fixed accuracy; pairs of the units whose relation is the strongest."""

    def __init__(self, pool: Pool, accuracy: float = 0.9, spread: bool = True):
        self.pool, self.spread = pool, spread
        self.greedy = Greedy(pool, np.where(pool.majority > 0.5, accuracy, 1 - accuracy))

    def cluster(self, label, fresh):
        if label is None or fresh is None:
            fresh = None
            self.links, self.fresh, self.old = Grown(np.int32, np.int32, bool), [np.flatnonzero(self.pool.asked)], None
        else:
            self.fresh.append(fresh)
        return self.greedy.label(fresh), True

    def _follow(self, label: np.ndarray) -> None:
        """Bring ``force`` up to these labels and the answers since: one more than the strength of a pair that may be next, else zero."""
        p = self.pool
        if self.old is None:
            self.force = np.zeros(len(p.u), np.int32)
        fresh = np.concatenate([*self.fresh, np.empty(0, np.int64)]).astype(np.int64)
        self.fresh = []
        self.links.add(p.u[fresh], p.w[fresh], p.majority[fresh] > 0.5)
        mark = np.full(p.n, self.old is None)
        was = mark
        if self.old is not None:
            moved = np.flatnonzero(label != self.old)
            mark[self.old[moved]] = mark[label[moved]] = True
            was = mark[self.old]
        keys = np.unique(unit_keys(label, p.u[fresh], p.w[fresh]))
        ends = np.zeros(p.n, bool)
        ends[keys // p.n] = ends[keys % p.n] = True
        a, b, yes = self.links.columns()
        x, y = label[a], label[b]
        at = np.flatnonzero(mark[x] | mark[y] | (ends[x] & ends[y]))
        unit = unit_keys(label, a[at], b[at])
        known, back = np.unique(unit, return_inverse=True)
        strength = np.bincount(back[yes[at] == (x[at] == y[at])], minlength=len(known))
        ends[:] = False
        ends[lesser(keys, np.bincount(label, minlength=p.n))] = True
        some = p.pairs_at(was | (mark | ends)[label])
        unit = unit_keys(label, p.u[some], p.w[some])
        mine = was[p.u[some]] | was[p.w[some]] | mark[label[p.u[some]]] | mark[label[p.w[some]]] | np.isin(unit, keys)
        some, unit = some[mine], unit[mine]
        self.force[some] = 0
        free = ~p.asked[some]
        some, unit = some[free], unit[free]
        if self.spread:
            unit, first = np.unique(unit, return_index=True)
            some = some[first]
        place = np.minimum(np.searchsorted(known, unit), max(len(known) - 1, 0))
        self.force[some] = 1 + (np.where(known[place] == unit, strength[place], 0) if len(known) else 0)
        self.old = label

    def choose(self, label: np.ndarray, count: int) -> np.ndarray:
        self._follow(label)
        held = np.bincount(self.force)
        held[0] = 0
        enough = np.flatnonzero(np.cumsum(held[::-1]) >= count)
        if not len(enough):
            return self._choose(label, count)
        least = len(held) - 1 - int(enough[0])
        best = np.flatnonzero(self.force > least)
        best = best[np.argsort(-self.force[best], kind="stable")]
        return np.concatenate([best, np.flatnonzero(self.force == least)[: count - len(best)]])

    def _choose(self, label: np.ndarray, count: int) -> np.ndarray:
        p = self.pool
        keys, back = np.unique(unit_keys(label, p.u, p.w), return_inverse=True)
        same = label[p.u] == label[p.w]
        support = p.asked & ((p.majority > 0.5) == same)
        strength = np.bincount(back[support], minlength=len(keys))
        free = np.flatnonzero(~p.asked)
        order = free[np.lexsort((free, -strength[back[free]]))]
        if self.spread:  # one pair of each unit, then the next of each
            unit = back[order]
            turn = np.argsort(unit, kind="stable")
            first = np.concatenate([[0], np.flatnonzero(np.diff(unit[turn])) + 1])
            place = np.empty(len(unit), np.int64)
            place[turn] = np.arange(len(unit)) - np.repeat(first, np.diff(np.append(first, len(unit))))
            order = order[np.argsort(place, kind="stable")]
        return order[:count]


class Bottleneck:
    """The best path decides: its weight is that of its weakest edge.

    Both weights of a pair follow from the components of each level and the links between these, so there is no
    matrix of all pairs of records as in ``kernels.bottleneck``.
    """

    def __init__(self, pool: Pool):
        self.pool = pool

    def cluster(self, label, fresh):
        p = self.pool
        a, b, ratio = p.edges(p.ratio)
        q, r = np.round(ratio, 9), np.round(1 - ratio, 9)
        self.levels = []  # from weak to strong: weight, components, keys of components that a link tells apart
        for at in np.unique(np.concatenate([q, r])).tolist():
            if at > 0.5:
                own = components(p.n, a[q >= at], b[q >= at])
                keys = np.unique(unit_keys(own, a[r >= at], b[r >= at]))
                self.levels.append((at, own, keys[keys // p.n != keys % p.n]))
        return self._groups(), True

    def _groups(self) -> np.ndarray:
        """Components of the pairs whose positive path outweighs the negative: one component at the least level, told apart at none."""
        n = self.pool.n
        if not self.levels:
            return np.arange(n)
        low, top = self.levels[0][1], self.levels[-1][1]
        told = []
        for _, own, keys in self.levels:
            x, y = np.concatenate([keys // n, keys % n]), np.concatenate([keys % n, keys // n])
            order = np.argsort(x, kind="stable")
            told.append((own, y[order], np.searchsorted(x[order], np.arange(n + 1))))
        reps, mark, root = np.unique(top), np.zeros(n, bool), np.arange(n)
        reps = reps[np.argsort(low[reps], kind="stable")]
        for rest in np.split(reps, np.flatnonzero(np.diff(low[reps])) + 1):
            while len(rest) > 1:
                least, todo, rest = int(rest[0]), [int(rest[0])], rest[1:]
                while todo and len(rest):
                    x, apart = todo.pop(), np.zeros(len(rest), bool)
                    for own, other, at in told:
                        some = other[at[own[x]] : at[own[x] + 1]]
                        if len(some):
                            mark[some] = True
                            apart |= mark[own[rest]]
                            mark[some] = False
                    root[rest[~apart]] = least
                    todo += rest[~apart].tolist()
                    rest = rest[apart]
        return root[top]

    def _score(self, pairs: np.ndarray) -> np.ndarray:
        p = self.pool
        pos, neg = np.zeros(len(pairs)), np.zeros(len(pairs))
        for at, own, keys in self.levels:
            unit = unit_keys(own, p.u[pairs], p.w[pairs])
            pos[own[p.u[pairs]] == own[p.w[pairs]]] = at
            if len(keys):
                neg[keys[np.minimum(np.searchsorted(keys, unit), len(keys) - 1)] == unit] = at
        return np.maximum(pos, np.where(pos <= neg, 1 - neg, 0))

    def choose(self, label: np.ndarray, count: int) -> np.ndarray:
        p, found, got, size = self.pool, [], 0, 4096
        start = 0
        while got < count and start < len(p.order):  # no score is above one
            some = p.order[start : start + size]
            start, size = start + size, 2 * size
            some = some[~p.asked[some]]
            found.append(some[self._score(some) >= 1][: count - got])
            got += len(found[-1])
        if got == count:
            return np.concatenate([p.order[:0], *found])
        free = np.flatnonzero(~p.asked)
        return free[np.lexsort((p.hash[free], -self._score(free)))[:count]]


class Pivot:
    """[R] Pivots in hashed order, refinement by splitting and merging, then pairs by the benefit of merging."""

    def __init__(self, pool: Pool):
        self.pool = pool

    def cluster(self, label, fresh):
        p = self.pool
        a, b, q = p.edges(p.ratio)
        near: list[list[int]] = [[] for _ in range(p.n)]
        for x, y in zip(a[q > 0.5].tolist(), b[q > 0.5].tolist(), strict=True):
            near[x].append(y)
            near[y].append(x)
        out = np.full(p.n, -1)
        for x in np.argsort(mixed(np.arange(p.n) + p.seed), kind="stable").tolist():
            if out[x] < 0:
                out[x] = x
                for y in near[x]:
                    if out[y] < 0:
                        out[y] = x
        inside = out[a] == out[b]
        leave = np.bincount(a[inside], (1 - 2 * q[inside]), p.n) + np.bincount(b[inside], (1 - 2 * q[inside]), p.n)
        gone = np.flatnonzero(leave > 0)
        out[gone] = gone + p.n  # on their own
        out = np.unique(out, return_inverse=True)[1]
        cross = out[a] != out[b]
        x, y = np.minimum(out[a], out[b])[cross], np.maximum(out[a], out[b])[cross]
        return self._merged(x, y, 2 * q[cross] - 1)[out], True

    def _merged(self, x: np.ndarray, y: np.ndarray, gain: np.ndarray) -> np.ndarray:
        """The merges of ``agglomerate``, which stay inside components of positive sums."""
        n = self.pool.n
        mark = np.zeros(n, bool)
        mark[x[gain > 0]] = mark[y[gain > 0]] = True
        some = mark[x] & mark[y]
        x, y, gain = x[some], y[some], gain[some]
        keys, back = np.unique(x * n + y, return_inverse=True)
        up = keys[np.bincount(back, gain, len(keys)) > 1e-12]
        part = components(n, up // n, up % n)
        some = part[x] == part[y]
        return agglomerate(n, x[some], y[some], gain[some])

    def choose(self, label: np.ndarray, count: int) -> np.ndarray:
        """Pairs of clusters whose answers speak for merging, then those without a balance, which need no look at the others."""
        p = self.pool
        at = np.flatnonzero(p.asked)
        at = at[label[p.u[at]] != label[p.w[at]]]
        keys, back = np.unique(unit_keys(label, p.u[at], p.w[at]), return_inverse=True)
        gain = np.bincount(back, 2 * p.ratio[at] - 1, len(keys))
        up, told = gain > 1e-9, keys[np.abs(gain) > 1e-9]
        mark = np.zeros(p.n, bool)
        mark[keys[up] // p.n] = True
        some = p.pairs_at(mark[label])
        some = some[~p.asked[some]]
        unit = unit_keys(label, p.u[some], p.w[some])
        mine = np.isin(unit, keys[up])
        some, (unit, back, open_) = some[mine], np.unique(unit[mine], return_inverse=True, return_counts=True)
        worth = (gain[np.searchsorted(keys, unit)] / open_)[back]
        found = [some[np.lexsort((p.hash[some], -np.round(worth, 9)))[:count]]]
        got, start, size = len(found[0]), 0, 4096
        while got < count and start < len(p.order):
            some = p.order[start : start + size]
            start, size = start + size, 2 * size
            some = some[~p.asked[some] & (label[p.u[some]] != label[p.w[some]])]
            if len(told):
                unit = unit_keys(label, p.u[some], p.w[some])
                some = some[told[np.minimum(np.searchsorted(told, unit), len(told) - 1)] != unit]
            found.append(some[: count - got])
            got += len(found[-1])
        return np.concatenate(found) if got == count else self._choose(label, count)

    def _choose(self, label: np.ndarray, count: int) -> np.ndarray:
        p = self.pool
        keys, back = np.unique(unit_keys(label, p.u, p.w), return_inverse=True)
        same = label[p.u] == label[p.w]
        gain = np.bincount(back[p.asked & ~same], 2 * p.ratio[p.asked & ~same] - 1, len(keys))
        open_ = np.bincount(back[~p.asked], minlength=len(keys))
        free = np.flatnonzero(~p.asked & ~same)
        worth = gain[back[free]] / open_[back[free]]
        return free[np.lexsort((p.hash[free], -np.round(worth, 9)))[:count]]


def chooser(method: str, pool: Pool, samples: int):
    return {
        "reliability": lambda: Reliability(pool, samples),
        "reliability_size": lambda: Reliability(pool, samples, tie="size"),
        "tc": lambda: Transitive(pool),
        "dense": lambda: Density(pool, spread=False),
        "bdense": lambda: Density(pool),
        "minmax": lambda: Bottleneck(pool),
        "pivot": lambda: Pivot(pool),
        "random": lambda: Random(pool),
    }[method]()


def initial_pairs(pool: Pool, initial: int | str) -> np.ndarray:
    """Numbers of the first pairs: none, all, a spanning path of the records, or so many in hash order."""
    if initial == "all":
        return np.arange(len(pool.u))
    if initial == "spanning" or initial == -1:
        return np.flatnonzero(pool.w == pool.u + 1)
    return pool.order[: 0 if initial == "none" else int(initial)]


def run(pool: Pool, entity: np.ndarray, method: str, batch: int, initial: int | str, samples: int = 1000, target: float | None = 0.95, most_rounds: int | None = None, budget: int | None = None) -> pd.DataFrame:
    """Rows of rounds until the target F1, the budget or the pool's end; each run is timed on its own task's clock."""
    pick = chooser(method, pool, samples)
    start = initial_pairs(pool, initial)
    pool.asked[start] = True
    label, _ = pick.cluster(None, None)
    asked, rows = 0, []
    spent, renewed = 0.0, True
    values = np.unique(pool.ratio)
    odds = [np.log(np.maximum(x, 1e-9)) for x in (values, 1 - values)]
    seen = Grown(np.int32, np.int32, np.int16)
    measured, apart = None, np.zeros(len(values), np.int64)
    fresh = start
    for n in itertools.count():
        seen.add(pool.u[fresh], pool.w[fresh], np.searchsorted(values, pool.ratio[fresh]))
        a, b, q = seen.columns()
        if measured is None or (label is not measured and (label != measured).any()):
            p, r, f = f1_of(label, entity)
            apart, since = np.zeros(len(values), np.int64), 0
        else:
            since = len(a) - len(fresh)
        measured = label
        apart = apart + np.bincount(q[since:][label[a[since:]] != label[b[since:]]], minlength=len(values))
        loglik = float(odds[0] @ (np.bincount(q, minlength=len(values)) - apart) + odds[1] @ apart)  # votes take few values
        rows.append((n, len(start), asked, p, r, f, loglik, pick.reliability(label) if isinstance(pick, Reliability) else None, spent, renewed))
        if (target is not None and f >= target) or (budget is not None and asked >= budget) or n == most_rounds:
            break
        began = time.process_time()
        fresh = pick.choose(label, batch if budget is None else min(batch, budget - asked))
        if not len(fresh):
            break
        pool.asked[fresh] = True
        asked += len(fresh)
        label, renewed = pick.cluster(label, fresh)
        spent = (time.process_time() - began) * 1000
    return pd.DataFrame(rows, columns=["round", "n_initial", "n_next", "precision", "recall", "f1", "loglik", "reliability", "select_ms", "reclustered"])
