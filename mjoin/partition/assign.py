"""Regions of a cube: which region owns a cell, and which regions a tuple must be copied to."""

from __future__ import annotations

import itertools
from dataclasses import dataclass
from functools import cached_property

import numpy as np

from .curves import CURVES, cells

MOST_CELLS = 1 << 20


@dataclass(frozen=True)
class RegionAssignment:
    """owner: region of every cell (first dimension slowest); bits: log2 of the cells of each dimension."""

    bits: tuple[int, ...]
    k: int
    curve: str
    owner: np.ndarray

    def __post_init__(self):
        if len(self.owner) != 1 << sum(self.bits):
            raise ValueError("every cell needs one owner")

    @cached_property
    def routes(self) -> list[list[list[int]]]:
        """routes[i][c]: sorted regions that meet the slab at coordinate c of dimension i."""
        shaped = self.owner.reshape([1 << b for b in self.bits])
        met = lambda i, c: np.unique(np.take(shaped, c, axis=i))
        return [[met(i, c)[met(i, c) >= 0].tolist() for c in range(1 << b)] for i, b in enumerate(self.bits)]

    def shares(self) -> np.ndarray:
        """Cells of each region; cells that can hold no answer (owner -1) belong to none."""
        return np.bincount(self.owner[self.owner >= 0], minlength=self.k)

    def restricted(self, live: np.ndarray) -> RegionAssignment:
        """The same order of cells, with only the live ones dealt out, evenly again."""
        # the order within a region doesn't matter: regions are runs of one curve
        order = np.argsort(self.owner, kind="stable")
        owner = np.full(len(self.owner), -1, np.int64)
        kept = order[live[order]]
        k = max(1, min(self.k, len(kept)))
        owner[kept] = np.arange(len(kept)) * k // max(1, len(kept))
        return RegionAssignment(self.bits, k, self.curve, owner)


def default_bits(m: int, k: int) -> int:
    """Bits of each of m dimensions, for about eight cells a region or more."""
    return max(1, min(20 // m, int(np.ceil(np.log2(8 * k) / m))))


def balanced_bits(cards: list[float], total: int) -> tuple[int, ...]:
    """total bits dealt out one by one to the relation whose cell is the largest."""
    bits = [0] * len(cards)
    for _ in range(total):
        k = max(range(len(cards)), key=lambda i: cards[i] / (1 << bits[i]))
        bits[k] += 1
    return tuple(bits)


def assign_regions(m: int, k: int, curve: str = "hilbert", bits: int | tuple[int, ...] | str | None = None, cards: list[float] | None = None, seed: int = 0) -> RegionAssignment:
    """Cut the cells of an m-dimensional cube, in the order of a curve, into k runs of equal length (within one cell).

    grid cuts each dimension into equal slices whose numbers multiply to k, best for cards; random deals cells at
    random; auto takes the least score of hilbert, hilbert with balanced bits, and grid. bits: a number for all
    dimensions, one for each, or "balanced" by cards.
    """
    cards = list(cards) if cards is not None else [1.0] * m
    if curve == "auto":
        options = [assign_regions(m, k, c, b, cards) for c, b in (("hilbert", bits), ("hilbert", "balanced"), ("grid", bits))]
        return min(options, key=lambda a: partition_score(a, cards))
    each = bits if isinstance(bits, int) else default_bits(m, k)
    shape = balanced_bits(cards, each * m) if bits == "balanced" else tuple(bits) if isinstance(bits, tuple | list) else (each,) * m
    if sum(shape) > 20:
        raise ValueError(f"{1 << sum(shape)} cells are too many; at most {MOST_CELLS}")
    total = 1 << sum(shape)
    if not 1 <= k <= total:
        raise ValueError(f"{k} regions do not fit {total} cells")
    grid = cells(shape)
    if curve == "grid":
        factors = min(_factorings(k, [1 << b for b in shape]), key=lambda f: sum(c * k / n for c, n in zip(cards, f, strict=True)), default=None)
        if factors is None:
            return assign_regions(m, k, "hilbert", shape, cards)
        owner = np.zeros(total, np.int64)
        for d, n in enumerate(factors):
            owner = owner * n + grid[:, d] * n // (1 << shape[d])
        return RegionAssignment(shape, k, curve, owner)
    if curve == "random":
        position = np.random.default_rng(seed).permutation(total)
    else:
        # A cube of the longest side, of which only the cells of the grid are visited.
        place = CURVES[curve](grid, max(shape))
        position = np.empty(total, np.int64)
        position[np.argsort(place, kind="stable")] = np.arange(total)
    return RegionAssignment(shape, k, curve, position * k // total)


def _factorings(k: int, sides: list[int]):
    if len(sides) == 1:
        return [(k,)] if k <= sides[0] else []
    return [(f, *rest) for f in range(1, min(k, sides[0]) + 1) if k % f == 0 for rest in _factorings(k // f, sides[1:])]


def live_cells(bits: tuple[int, ...], bounds: list[list[tuple] | None], comparisons: list[tuple[int, str, int]]) -> np.ndarray:
    """Which cells can hold an answer: bounds[i][c] is the (least, greatest) value at coordinate c of dimension i, or None for any.

    comparisons are (dimension, operator, dimension) of the values that the coordinates are ranges of. None as an end is unbounded.
    """
    grid = cells(bits)
    live = np.ones(len(grid), bool)
    for i, op, j in comparisons:
        if bounds[i] is None or bounds[j] is None:
            continue
        table = np.array([[_possible(a, op, b) for b in bounds[j]] for a in bounds[i]])
        live &= table[grid[:, i], grid[:, j]]
    return live


def _possible(a: tuple, op: str, b: tuple) -> bool:
    (lo_a, hi_a), (lo_b, hi_b) = a, b
    below = lambda x, y, strict: x is None or y is None or (x < y if strict else x <= y)
    if op in ("<", "<="):
        return below(lo_a, hi_b, op == "<")
    if op in (">", ">="):
        return below(lo_b, hi_a, op == ">")
    if op == "=":
        return below(lo_a, hi_b, False) and below(lo_b, hi_a, False)
    return not (lo_a == hi_a == lo_b == hi_b and lo_a is not None)


def copies_by_relation(a: RegionAssignment, cards: list[float]) -> list[float]:
    """Tuple copies of each relation, for tuples spread evenly over the coordinates."""
    return [n / (1 << b) * sum(map(len, routes)) for n, b, routes in zip(cards, a.bits, a.routes, strict=True)]


def partition_score(a: RegionAssignment, cards: list[float]) -> float:
    """All tuple copies that are sent to regions."""
    return float(sum(copies_by_relation(a, cards)))


def duplication_factor(a: RegionAssignment, i: int) -> float:
    """Copies of one tuple of relation i, on average."""
    return sum(map(len, a.routes[i])) / (1 << a.bits[i])


def is_balanced(a: RegionAssignment, cards: list[float], slack: float = 1e-9) -> bool:
    """Whether all relations are copied in equal number."""
    each = copies_by_relation(a, cards)
    return max(each) - min(each) <= slack * max(each)


def min_score_bruteforce(m: int, side: int, k: int) -> int:
    """Least score of any fair cut of a tiny cube (one tuple a coordinate), by trying all of them."""
    n = side**m
    sizes = sorted(n * (r + 1) // k - n * r // k for r in range(k))
    grid = list(itertools.product(range(side), repeat=m))
    best = None

    def walk(left: frozenset, sizes: list[int], score: int):
        nonlocal best
        if best is not None and score >= best:
            return
        if not sizes:
            best = score
            return
        first = min(left)
        for rest in itertools.combinations(sorted(left - {first}), sizes[0] - 1):
            part = (first, *rest)
            touched = sum(len({grid[c][d] for c in part}) for d in range(m))
            walk(left - set(part), sizes[1:], score + touched)

    walk(frozenset(range(n)), sizes, 0)
    return best
