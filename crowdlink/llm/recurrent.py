"""Gated recurrent language model with a class-factored output, in numpy.

A token is one of ``head`` frequent words, sorted into equal classes by frequency, or the tail. The state
gives the class, the class and the state give the word; a tail word's share of the tail is left to corpus
counts. Training is truncated backpropagation over windows of lanes of whole documents, and the state is
carried from window to window until a document ends.
"""

from __future__ import annotations

import ctypes
import heapq
from dataclasses import dataclass
from pathlib import Path

import numpy as np

LANES, WINDOW, LONGEST = 512, 24, 192
#: With fewer lanes than this a window has more steps, up to LONGEST, as the last documents of a call are the long ones.
FULL = 256
#: Rows of a longer run are summed by themselves.
RUN = 24


def one_thread() -> None:
    """Tasks run side by side on small matrices, where more threads of the algebra library only wait for each other."""
    for lib in (Path(np.__file__).parents[1] / "numpy.libs").glob("*openblas*"):
        put = getattr(ctypes.CDLL(str(lib)), "scipy_openblas_set_num_threads64_", None)
        if put:
            put(1)


def lanes_of(texts: list[np.ndarray], count: int) -> tuple[np.ndarray, np.ndarray]:
    """Matrices (steps, lanes) of tokens and of text numbers; -1 where a lane has run out."""
    order = sorted(range(len(texts)), key=lambda n: -len(texts[n]))
    lanes: list[list[int]] = [[] for _ in range(min(count, max(len(texts), 1)))]
    heap = [(0, k) for k in range(len(lanes))]
    for n in order:
        size, k = heapq.heappop(heap)
        lanes[k].append(n)
        heapq.heappush(heap, (size + len(texts[n]), k))
    steps = max(size for size, _ in heap)
    tokens, owner = np.full((len(lanes), steps), -1, np.int32), np.full((len(lanes), steps), -1, np.int32)
    for k, own in enumerate(lanes):
        if own:
            flat = np.concatenate([texts[n] for n in own])
            tokens[k, : len(flat)] = flat
            owner[k, : len(flat)] = np.repeat(own, [len(texts[n]) for n in own])
    turn = np.argsort([-size for size, _ in sorted(heap, key=lambda x: x[1])], kind="stable")  # long lanes first
    tokens = np.ascontiguousarray(tokens.T[:, turn])
    return tokens, np.ascontiguousarray(owner.T[:, turn])


def _before(tokens: np.ndarray, owner: np.ndarray, start: int, end: int, live: int, first: int) -> tuple[np.ndarray, np.ndarray]:
    """The token read at each place of the first ``live`` lanes, and whether a text begins there."""
    own, last = owner[start:end, :live], max(start - 1, 0)
    opens = np.ones(own.shape, bool)
    skip = 1 if start == 0 else 0
    opens[skip:] = own[skip:] != owner[last : end - 1, :live]
    before = np.full(own.shape, first, np.int32)
    before[skip:] = np.where(opens[skip:] | (own[skip:] < 0), first, tokens[last : end - 1, :live])
    return before, opens


def _width(live: int, least: int = WINDOW) -> int:
    return min(LONGEST, max(least, least * FULL // live))


def _rows(x: np.ndarray, at: np.ndarray) -> np.ndarray:
    """Rows of ``x``; several times faster than an index array on short rows."""
    return np.take(x, at, axis=0, mode="clip")


def _top(a: np.ndarray) -> np.ndarray:
    """The greatest of each short row, as a column; numpy is slow along short rows."""
    return np.ascontiguousarray(a.T).max(axis=0)[:, None]


def _sums(rows: np.ndarray, at: np.ndarray) -> tuple[np.ndarray, np.ndarray]:
    """The sum of each run of rows, long runs first, and the runs' numbers; ``at`` holds where runs begin and the end.

    Long runs are summed one by one, of the others the first rows, the second rows and so on; several times faster
    than ``reduceat``.
    """
    size = np.diff(at)
    by = np.argsort(-size, kind="stable")
    size, begin = size[by], at[by]
    out = _rows(rows, begin)
    more = len(size) - np.searchsorted(size[::-1], np.arange(RUN + 1), "right")  # runs longer than 0, 1, 2 and so on
    for k in range(more[RUN]):
        np.dot(np.ones(size[k], rows.dtype), rows[begin[k] : begin[k] + size[k]], out=out[k])
    for k in range(1, RUN):
        part = slice(more[RUN], more[k])
        out[part] += _rows(rows, begin[part] + k)
    return by, out


def _tame(weights: np.ndarray, bias: np.ndarray) -> bool:
    """Whether no score can leave the range in which sums of exponentials are exact: a state is within -1 and 1."""
    return bool((np.abs(weights).sum(axis=-2) + np.abs(bias)).max() < 60)


@dataclass
class Recurrent:
    head: int  # words with a number of their own; ``head`` itself is the tail
    size: int
    classes: int
    p: dict[str, np.ndarray]

    @classmethod
    def fresh(cls, head: int, size: int = 24, classes: int = 32, seed: int = 7) -> Recurrent:
        rng = np.random.default_rng(seed)
        each = -(-head // classes)
        draw = lambda *shape: (rng.standard_normal(shape) * (1 / np.sqrt(size))).astype(np.float32)
        p = {"x": draw(head + 1, 3 * size), "u": draw(size, 3 * size), "c": draw(size, classes + 1), "cb": np.zeros(classes + 1, np.float32), "w": draw(classes, size, each), "wb": np.zeros((classes, each), np.float32)}
        spare = classes * each - head  # the last class may have places without a word
        if spare:
            p["wb"].reshape(-1)[head:] = -30
        return cls(head, size, classes, p)

    @property
    def each(self) -> int:
        return self.p["w"].shape[2]

    def _forward(self, before: np.ndarray, opens: np.ndarray, h: np.ndarray, keep: bool = True) -> tuple[np.ndarray, ...]:
        """One window, step by step; all that comes back is (steps, features, lanes), so that a gate is one block of memory.

        Without ``keep`` only the states, the last of the results, hold all steps.
        """
        s, (steps, lanes) = self.size, before.shape
        kind = self.p["u"].dtype
        half = np.ones((3 * s, 1), kind)  # a sigmoid is a hyperbolic tangent of half its input
        half[: 2 * s] = 0.5
        x = np.ascontiguousarray(_rows(self.p["x"] * half.T, before).transpose(0, 2, 1))
        u = self.p["u"].T * half
        deep = steps if keep else 1
        into, n, states = (np.empty((d, s, lanes), kind) for d in (deep, deep, steps))
        gates, hu = np.empty((deep, 2 * s, lanes), kind), np.empty((deep, 3 * s, lanes), kind)
        for t in range(steps):
            k = t if keep else 0
            if opens[t].any():
                np.multiply(h, ~opens[t], out=into[k])
            else:
                into[k] = h
            np.matmul(u, into[k], out=hu[k])
            g = np.add(x[t, : 2 * s], hu[k, : 2 * s], out=gates[k])
            np.tanh(g, out=g)
            g *= kind.type(0.5)
            g += kind.type(0.5)
            m = np.multiply(g[s:], hu[k, 2 * s :], out=n[k])
            m += x[t, 2 * s :]
            np.tanh(m, out=m)
            h = np.subtract(into[k], m, out=states[t])
            h *= g[:s]
            h += m
        return into, gates, hu[:, 2 * s :], n, states

    def _kept(self, states: np.ndarray, valid: np.ndarray) -> np.ndarray:
        """States at the valid places, one row each."""
        return _rows(states.transpose(0, 2, 1).reshape(-1, self.size), np.flatnonzero(valid))

    def _class_scores(self, h: np.ndarray) -> np.ndarray:
        """Scores of the classes; a softmax of each row gives their shares, and no exponential overflows."""
        a = h @ self.p["c"]
        a += self.p["cb"]
        if not _tame(self.p["c"], self.p["cb"]):
            a -= _top(a)
        return a

    def _by_class(self, h: np.ndarray, cls: np.ndarray) -> tuple[np.ndarray, list[slice], np.ndarray, np.ndarray]:
        """Places of known words ordered by class, the part of each class, their states and their scores in the class."""
        order = np.argsort(cls.astype(np.int16), kind="stable")
        bounds = np.searchsorted(cls[order], np.arange(self.classes + 1))
        order = order[: bounds[-1]]
        h = _rows(h, order)
        parts = [slice(a, b) for a, b in zip(bounds[:-1], bounds[1:], strict=True)]
        out = np.empty((len(order), self.each), h.dtype)
        for k, part in enumerate(parts):
            if part.start < part.stop:
                np.matmul(h[part], self.p["w"][k], out=out[part])
                out[part] += self.p["wb"][k]
        if not _tame(self.p["w"], self.p["wb"]):
            out -= _top(out)
        return order, parts, h, out

    def scores(self, h: np.ndarray, token: np.ndarray) -> np.ndarray:
        """Natural log probability of each token (or of the tail) after each state."""
        cls = np.where(token < self.head, token // self.each, self.classes)
        a = self._class_scores(h)
        out = a[np.arange(len(token)), cls]
        out -= np.log(np.exp(a, out=a) @ np.ones(a.shape[1], np.float32))
        order, _, _, a = self._by_class(h, cls)
        out[order] += a[np.arange(len(order)), token[order] % self.each]
        out[order] -= np.log(np.exp(a, out=a) @ np.ones(self.each, np.float32))
        return out

    def score_texts(self, texts: list[np.ndarray], first: int) -> np.ndarray:
        """Natural log probability of each whole text; ``first`` is the token read before a text begins."""
        total = np.zeros(len(texts))
        if not texts:
            return total
        # as many lanes as keep the matrices within about twice the tokens, if one text is very long
        each = [len(t) for t in texts]
        tokens, owner = lanes_of(texts, min(LANES, max(64, 2 * sum(each) // max(each))))
        h = np.zeros((self.size, tokens.shape[1]), np.float32)
        start = end = 0
        while (start := end) < len(tokens):
            live = int((owner[start] >= 0).sum())  # the lanes that go on are the first ones
            end = min(start + _width(live), len(tokens))
            piece, own = tokens[start:end, :live], owner[start:end, :live]
            before, opens = _before(tokens, owner, start, end, live, first)
            states = self._forward(before, opens, h[:, :live], keep=False)[-1]
            h, valid = states[-1], own >= 0
            s = self.scores(self._kept(states, valid), piece[valid])
            total += np.bincount(own[valid], s, len(texts))
        return total

    def flat(self) -> np.ndarray:
        """All weights in one row."""
        return np.concatenate([x.ravel() for x in self.p.values()])

    def put(self, flat: np.ndarray) -> None:
        at = 0
        for k, x in self.p.items():
            self.p[k] = flat[at : at + x.size].reshape(x.shape).copy()
            at += x.size

    def train(self, texts: list[np.ndarray], first: int, rate: float = 4e-3, state: dict | None = None, lanes: int = LANES, window: int = WINDOW) -> None:
        """One pass of Adam over truncated windows; the hidden state flows on, the gradient stops at a window's start.

        The loss is taken at every place. A step is as long as its window has places, against the greatest window so
        far, so that the last windows, of one long document, do not undo what the others taught. Rows of words that a
        window does not touch keep their weights and moments. ``state`` holds the moments between calls.
        """
        state = {} if state is None else state
        if not state:
            state |= {"no": 0, "m": {k: np.zeros_like(x) for k, x in self.p.items()}, "v": {k: np.zeros_like(x) for k, x in self.p.items()}}
        each = [len(t) for t in texts]
        tokens, owner = lanes_of(texts, min(lanes, max(32, 2 * sum(each) // max(each))))
        h = np.zeros((self.size, tokens.shape[1]), np.float32)
        start = end = most = 0
        while (start := end) < len(tokens):
            live = int((owner[start] >= 0).sum())  # the lanes that go on are the first ones
            end = min(start + _width(live, window), len(tokens))
            piece, own = tokens[start:end, :live], owner[start:end, :live]
            before, opens = _before(tokens, owner, start, end, live, first)
            run = self._forward(before, opens, h[:, :live])
            h = run[-1][-1]
            places = int((own >= 0).sum())
            most = max(most, places)
            self._adam(self._gradients(piece, own, before, opens, run), np.unique(before), np.unique(piece[(own >= 0) & (piece < self.head)] // self.each), rate * places / most, state)

    def _adam(self, g: dict[str, np.ndarray], words: np.ndarray, classes: np.ndarray, rate: float, state: dict) -> None:
        state["no"] += 1
        rows = {"x": words, "w": classes, "wb": classes}
        g = {k: _rows(x, rows[k]) if k in rows else x for k, x in g.items()}
        clip = np.float32(min(1.0, 5.0 / (np.sqrt(sum(float((x * x).sum()) for x in g.values())) + 1e-9)))
        eta, far = np.float32(rate / (1 - 0.9 ** state["no"])), np.float32(1 / (1 - 0.99 ** state["no"]))
        for k, x in g.items():
            at = rows.get(k, slice(None))
            m, v, p = (_rows(y, at) if k in rows else y for y in (state["m"][k], state["v"][k], self.p[k]))
            x *= clip
            m *= np.float32(0.9)
            m += np.float32(0.1) * x
            x *= x
            x *= np.float32(0.01)
            v *= np.float32(0.99)
            v += x
            p -= eta * m / (np.sqrt(v * far) + np.float32(1e-8))
            if k in rows:
                state["m"][k][at], state["v"][k][at], self.p[k][at] = m, v, p

    def _gradients(self, piece: np.ndarray, own: np.ndarray, before: np.ndarray, opens: np.ndarray, run: tuple[np.ndarray, ...]) -> dict[str, np.ndarray]:
        g = {k: np.zeros_like(v) for k, v in self.p.items()}
        into, gates, hn, n, states = run
        valid = own >= 0
        h, token = self._kept(states, valid), piece[valid]
        scale = np.float32(1 / max(len(token), 1))
        cls = np.where(token < self.head, token // self.each, self.classes)
        a = self._class_scores(h)
        np.exp(a, out=a)
        a *= scale / (a @ np.ones((a.shape[1], 1), np.float32))
        a[np.arange(len(token)), cls] -= scale
        g["c"], g["cb"] = h.T @ a, a.sum(axis=0)
        dh = a @ self.p["c"].T
        order, parts, known, b = self._by_class(h, cls)
        np.exp(b, out=b)
        b *= scale / (b @ np.ones((self.each, 1), np.float32))
        b[np.arange(len(order)), token[order] % self.each] -= scale
        back = np.empty_like(known)
        for k, part in enumerate(parts):
            if part.start < part.stop:
                g["w"][k], g["wb"][k] = known[part].T @ b[part], b[part].sum(axis=0)
                np.matmul(b[part], self.p["w"][k].T, out=back[part])
        dh[order] += back
        outer = np.zeros((*own.shape, self.size), h.dtype)
        outer.reshape(-1, self.size)[np.flatnonzero(valid)] = dh
        d, du = self._backward(np.ascontiguousarray(outer.transpose(0, 2, 1)), opens, into, gates, hn, n)
        g["u"] = np.matmul(into, du.transpose(0, 2, 1)).sum(axis=0)
        du[:, 2 * self.size :] = d  # what reaches the words read is not reset
        dx = du.transpose(0, 2, 1).reshape(-1, 3 * self.size)
        word = before.ravel()
        order = np.argsort(word.astype(np.uint16 if self.head < 1 << 16 else np.uint32), kind="stable")  # 16 bits are sorted by radix
        word = word[order]
        at = np.append(np.flatnonzero(np.append(True, word[1:] != word[:-1])), len(word))
        by, sums = _sums(_rows(dx, order), at)
        g["x"][word[at[by]]] = sums
        return g

    def _backward(self, d: np.ndarray, opens: np.ndarray, into: np.ndarray, gates: np.ndarray, hn: np.ndarray, n: np.ndarray) -> tuple[np.ndarray, np.ndarray]:
        """Gradients of the candidate and of all three inputs by the state; ``d`` begins as the losses' own part."""
        s, steps = self.size, len(d)
        du = np.empty((steps, 3, s, d.shape[2]), d.dtype)
        carry = np.zeros_like(d[0])
        rest, new = np.empty_like(carry), np.empty_like(carry)
        for t in range(steps - 1, -1, -1):  # all of a step while it is in the cache
            z, r, by = gates[t, :s], gates[t, s:], du[t]
            d[t] += carry
            np.subtract(1, z, out=rest)
            np.multiply(n[t], n[t], out=new)
            np.subtract(1, new, out=new)
            new *= rest
            np.subtract(into[t], n[t], out=by[0])
            by[0] *= z
            by[0] *= rest
            np.multiply(new, r, out=by[2])
            np.multiply(by[2], hn[t], out=by[1])
            by[1] *= np.subtract(1, r, out=rest)
            by *= d[t]
            carry = self.p["u"] @ by.reshape(3 * s, -1)
            carry += np.multiply(d[t], z, out=rest)
            if opens[t].any():
                carry *= ~opens[t]
            d[t] *= new
        return d, du.reshape(steps, 3 * s, -1)
