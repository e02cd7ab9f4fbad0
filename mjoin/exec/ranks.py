"""Sums over the rows of one side that meet each row of the other, by sorted ranks: no pairs are visited."""

from __future__ import annotations

import itertools

import numpy as np

#: Conditions <> that met_sums takes: each doubles its passes.
MOST_UNEQUAL = 4
_RANKED = ("<", "<=", ">=", ">")


def prefix_sums(ranks: np.ndarray, weights: np.ndarray | None, upto: np.ndarray, below: np.ndarray, start: np.ndarray | None = None) -> np.ndarray:
    """For each (p, r) of upto and below: the sum of weights[i] over start <= i < p with ranks[i] < r <= len(ranks).

    Bit by bit from the highest: positions are dealt stably by the bit, and a query follows the bits of r. No start: from 0;
    no weights: 1 each.
    """
    kind = np.int32 if len(ranks) < 1 << 31 else np.int64
    ranks, below, hi, total = ranks.astype(kind), below.astype(kind), upto.astype(kind), np.zeros(len(upto), np.int64)
    lo = np.zeros(len(upto), kind) if start is None else start.astype(kind)
    for bit in range(len(ranks).bit_length() - 1, -1, -1):
        zero = (ranks >> bit & 1) == 0
        n0 = np.zeros(len(ranks) + 1, kind)
        np.cumsum(zero, out=n0[1:])
        w0 = n0 if weights is None else np.concatenate(([0], np.cumsum(np.where(zero, weights, 0))))
        one = (below >> bit & 1) == 1
        lo0, hi0 = n0[lo], n0[hi]
        total += np.where(one, hi0 - lo0 if weights is None else w0[hi] - w0[lo], 0)
        lo, hi = np.where(one, lo + n0[-1] - lo0, lo0), np.where(one, hi + n0[-1] - hi0, hi0)
        ranks = np.concatenate((ranks[zero], ranks[~zero]))
        if weights is not None:
            weights = np.concatenate((weights[zero], weights[~zero]))
    return total


def _met(x: np.ndarray, op: str, values: np.ndarray) -> np.ndarray:
    """How many of the sorted values each x meets by op: the last ones for < and <=, the first ones for > and >=."""
    at = np.searchsorted(values, x, "right" if op in ("<", ">=") else "left")
    return len(values) - at if op in ("<", "<=") else at


def local_sums(pairs: list[tuple[np.ndarray, np.ndarray, str]], weights: np.ndarray) -> np.ndarray:
    """For each left row the sum of the weights of the right rows that meet both conditions (left values, right values, operator)."""
    (x, u, first), (y, v, second) = pairs
    order = np.argsort(v, kind="stable")
    upto = _met(y, second, v[order])
    if second in ("<", "<="):
        order = order[::-1]
    rank = np.empty(len(u), np.int64)
    by = np.argsort(u, kind="stable")
    below = _met(x, first, u[by])
    rank[by[::-1] if first in ("<", "<=") else by] = np.arange(len(u))
    return prefix_sums(rank[order], weights[order], upto, below)


def ranked(operators: list[str]) -> bool:
    """Whether met_sums takes conditions of these operators."""
    return sum(op in _RANKED for op in operators) <= 2 and operators.count("<>") <= MOST_UNEQUAL


def met_sums(pairs: list[tuple[np.ndarray, np.ndarray, str]], weights: np.ndarray | None = None) -> np.ndarray:
    """For each left row the sum of the weights (none: 1 each) of the right rows that meet all conditions (left values, right values, operator).

    Up to two of < <= >= > go by ranks and = by groups of equal values; for <> the sums under = are taken off again.
    """
    order, equal, other = ([p for p in pairs if p[2] in ops] for ops in (_RANKED, ("=",), ("<>",)))
    total = np.zeros(len(pairs[0][0]), np.int64)
    for n in range(len(other) + 1):
        for some in itertools.combinations(other, n):
            total += (-1) ** n * _sums_in_groups(order, [*equal, *some], len(pairs[0][0]), len(pairs[0][1]), weights)
    return total


def _sums_in_groups(order: list, equal: list, n_left: int, n_right: int, weights: np.ndarray | None) -> np.ndarray:
    """met_sums of at most two inequalities and equalities: right rows lie group by group, within one by the last inequality's values."""
    left, right = np.zeros(n_left, np.int64), np.zeros(n_right, np.int64)
    for x, v, _ in equal:
        values = np.unique(np.concatenate((x, v)))
        codes = np.concatenate((left, right)) * len(values) + np.searchsorted(values, np.concatenate((x, v)))
        codes = np.unique(codes, return_inverse=True)[1].reshape(-1)
        left, right = codes[:n_left], codes[n_left:]
    place, width, cut, down = np.zeros(n_right, np.int64), 1, None, True
    if order:
        y, v, op = order[-1]
        values, place = np.unique(v, return_inverse=True)
        place, width, down = place.reshape(-1), len(values) + 1, op in (">", ">=")
        cut = np.searchsorted(values, y, "right" if op in ("<", ">=") else "left")
    key = right * width + place
    by = np.argsort(key, kind="stable")
    key = key[by]
    lo, hi = np.searchsorted(key, left * width), np.searchsorted(key, (left + 1) * width)
    if order:
        at = np.searchsorted(key, left * width + cut)
        lo, hi = (lo, at) if down else (at, hi)
    if len(order) < 2:
        sums = np.concatenate(([0], np.cumsum(np.ones(n_right, np.int64) if weights is None else weights[by])))
        return sums[hi] - sums[lo]
    x, u, op = order[0]
    along = np.argsort(u, kind="stable")
    rank = np.empty(n_right, np.int64)
    rank[along[::-1] if op in ("<", "<=") else along] = np.arange(n_right)
    return prefix_sums(rank[by], None if weights is None else weights[by], hi, _met(x, op, u[along]), lo)
