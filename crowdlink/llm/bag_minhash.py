"""Weighted minimum hashing of multisets by Poisson processes over discretised weights.

Every element owns a Poisson process in time and weight. Its weight axis is cut into the dyadic ranges
[0,1), [1,2), [2,4), [4,8) ...; a point is a time, a whole weight below which it does not count, and one
of the signature's registers. A register keeps the earliest point whose weight lies below the element's
own weight. Two multisets agree in a register with the probability of their weighted Jaccard similarity.
Ranges are opened from the earliest times on, and only up to the time by which all registers of a text
are filled, so the work hardly depends on the weights.
"""

from __future__ import annotations

import numpy as np

from crowdlink.llm.text import mix

_U64 = np.uint64


def _unit(x: np.ndarray) -> np.ndarray:
    """Even numbers in (0, 1]."""
    return ((x >> _U64(11)).astype(np.float64) + 1.0) * (1.0 / (1 << 53))


def signatures(elements: np.ndarray, weights: np.ndarray, owner: np.ndarray, texts: int, registers: int) -> np.ndarray:
    """Array (texts, registers) of 64-bit values; a text without elements has zeros.

    ``elements`` are hashes, distinct within an owner, with whole weights of one or more.
    """
    total = np.bincount(owner, weights=weights, minlength=texts)
    best_time = np.full(texts * registers, np.inf)
    best_mark = np.zeros(texts * registers, _U64)
    bound = np.where(total > 0, (np.log(registers) + 5.0) / np.maximum(total, 1e-300), 0.0)
    # a process: element, range number, time reached, points drawn, as rows of parallel arrays
    ranges = [(elements, np.zeros(len(elements), np.int64), owner, weights)]
    top, level = weights, 1
    while (more := np.flatnonzero(top > (1 << (level - 1)))).size:
        elements, owner, top = elements[more], owner[more], top[more]
        ranges.append((elements, np.full(len(more), level), owner, top))
        level += 1
    element, level_of, own, weight = (np.concatenate(x) for x in zip(*ranges, strict=True))
    low = np.where(level_of == 0, 0, 1 << np.maximum(level_of - 1, 0))
    width = np.where(level_of == 0, 1, low)
    rate = registers * width.astype(np.float64)
    time = np.zeros(len(element))
    with np.errstate(over="ignore"):
        state = mix(element ^ (level_of.astype(_U64) * _U64(0xA0761D6478BD642F)))
    done = total <= 0
    waiting = np.arange(len(element))
    while waiting.size:
        late: list[np.ndarray] = []
        live = waiting
        while live.size:
            with np.errstate(over="ignore"):
                step = mix(state[live] + _U64(0x9E3779B97F4A7C15))
                spot = mix(step ^ _U64(0x8EBC6AF09C88C6E3))
            due = time[live] - np.log(_unit(step)) / rate[live]
            over = due > bound[own[live]]
            if over.any():  # drawn again from the same state if the bound is moved
                late.append(live[over])
                live, due, step, spot = live[~over], due[~over], step[~over], spot[~over]
            time[live], state[live] = due, step
            counts = (spot >> _U64(32)) % width[live].astype(_U64) + low[live].astype(_U64) < weight[live].astype(_U64)
            hit = live[counts]
            slot = own[hit] * registers + (spot[counts] & _U64(0xFFFFFFFF)).astype(np.int64) % registers
            np.minimum.at(best_time, slot, due[counts])
            won = best_time[slot] == due[counts]
            best_mark[slot[won]] = step[counts][won]
        filled = np.isfinite(best_time.reshape(texts, registers)).all(axis=1)
        done |= filled
        waiting = np.concatenate(late) if late else waiting[:0]
        waiting = waiting[~done[own[waiting]]]
        bound *= 2
    return best_mark.reshape(texts, registers)
