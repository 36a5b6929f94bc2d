"""Vectorised searches in sorted runs of one array, with the comparisons that they take."""

from __future__ import annotations

import numpy as np


def bisect(keys: np.ndarray, q: np.ndarray, lo: np.ndarray, hi: np.ndarray) -> tuple[np.ndarray, np.ndarray]:
    """Last index in [lo, hi) whose key is not above q, or lo; and the comparisons."""
    lo, hi, steps = lo.copy(), hi.copy(), np.zeros(len(q), np.int64)
    while (wide := hi - lo > 1).any():
        mid = (lo + hi) // 2
        below = wide & (keys[np.minimum(mid, len(keys) - 1)] <= q)
        lo, hi = np.where(below, mid, lo), np.where(wide & ~below, mid, hi)
        steps += wide
    return lo, steps


def gallop(keys: np.ndarray, q: np.ndarray, lo: np.ndarray, hi: np.ndarray, guess: np.ndarray) -> tuple[np.ndarray, np.ndarray]:
    """The same, outwards from a guess with doubling steps, then by halving the last step."""
    guess = np.clip(guess, lo, hi - 1)
    right = keys[guess] <= q
    steps, reach = np.ones(len(q), np.int64), np.ones(len(q), np.int64)
    a, b = guess.copy(), guess.copy()  # the answer lies in [a, b) once the walk ends
    b[right] += 1
    going = np.ones(len(q), bool)
    while going.any():
        up, down = going & right, going & ~right
        ahead = np.minimum(guess + reach, hi)
        more = up & (ahead < hi)
        below = np.zeros(len(q), bool)
        below[more] = keys[ahead[more]] <= q[more]
        a, b = np.where(below, ahead, a), np.where(up, ahead, b)
        back = np.maximum(guess - reach, lo)
        above = np.zeros(len(q), bool)
        far = down & (back > lo)
        above[far] = keys[back[far]] > q[far]
        b, a = np.where(above, back, b), np.where(down, back, a)
        steps += more | far
        going = below | above
        reach *= 2
    got, halved = bisect(keys, q, a, np.maximum(b, a + 1))
    return got, steps + halved
