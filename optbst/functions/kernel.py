"""Interval dynamic programs for optimal search trees, on one machine's arrays.

Cell (i, j), 0 <= i <= j <= n, is the best tree over keys i+1..j: its cost and the leftmost best cut k
(the root is key k+1). Cells of one diagonal are evaluated together.
"""

from __future__ import annotations

from dataclasses import dataclass

import numpy as np

#: Stands for a cell that is not evaluated.
UNSET = np.iinfo(np.int64).max


@dataclass
class Weights:
    """hit[1..n] (hit[0] is 0) and miss[0..n], with prefix sums; w(i, j) is the weight of a cell."""

    hit: np.ndarray
    miss: np.ndarray

    def __post_init__(self) -> None:
        self.hit, self.miss = np.asarray(self.hit, np.int64).copy(), np.asarray(self.miss, np.int64)
        if len(self.hit) != len(self.miss) or not len(self.miss):
            raise ValueError("hit and miss need a row for each of 0..n")
        self.hit[0] = 0
        if (self.hit < 0).any() or (self.miss < 0).any():
            raise ValueError("weights must not be negative")
        total = int(self.hit.sum(dtype=object)) + int(self.miss.sum(dtype=object))
        if total * (len(self.miss) + 1) >= 1 << 63:
            raise OverflowError("total weight times n + 2 must stay below 2^63; scale the weights")
        self.p, self.q = np.cumsum(self.hit), np.cumsum(self.miss)

    @property
    def n(self) -> int:
        return len(self.miss) - 1

    def w(self, i: np.ndarray, j: np.ndarray) -> np.ndarray:
        return self.p[j] - self.p[i] + self.q[j] - self.q[i] + self.miss[i]


@dataclass
class Solution:
    """Upper-triangular cost and cut tables, and how many candidates were compared on each diagonal."""

    cost: np.ndarray
    split: np.ndarray
    candidates: np.ndarray

    @property
    def optimum(self) -> int:
        return int(self.cost[0, -1])


def _tables(w: Weights) -> tuple[np.ndarray, np.ndarray]:
    size = w.n + 1
    cost, split = np.full((size, size), UNSET, np.int64), np.full((size, size), -1, np.int32)
    at = np.arange(size)
    cost[at, at], split[at, at] = w.miss, at
    return cost, split


def leftmost_best(cost: np.ndarray, i: np.ndarray, j: np.ndarray, low: np.ndarray, high: np.ndarray) -> tuple[np.ndarray, np.ndarray, int]:
    """For each cell the least cost(i, k) + cost(k+1, j), low <= k <= high, its leftmost k, and all candidates."""
    width = high - low + 1
    start = np.cumsum(width) - width
    k = np.arange(width.sum()) - np.repeat(start - low, width)
    sums = cost[np.repeat(i, width), k] + cost[k + 1, np.repeat(j, width)]
    best = np.minimum.reduceat(sums, start)
    hit = np.flatnonzero(sums == np.repeat(best, width))
    cell = np.repeat(np.arange(len(i)), width)[hit]
    first = np.concatenate([[True], cell[1:] != cell[:-1]])
    return best, k[hit[first]], int(width.sum())


def solve_cubic(w: Weights) -> Solution:
    """Every cut of every cell: n(n+1)(n+2)/6 candidates."""
    cost, split = _tables(w)
    counts = np.zeros(w.n + 1, np.int64)
    for d in range(1, w.n + 1):
        i = np.arange(w.n - d + 1)
        best, cut, counts[d] = leftmost_best(cost, i, i + d, i, i + d - 1)
        cost[i, i + d], split[i, i + d] = best + w.w(i, i + d), cut
    return Solution(cost, split, counts)


def solve_windowed(w: Weights) -> Solution:
    """Only cuts between those of the two neighbouring cells: about two candidates a cell."""
    cost, split = _tables(w)
    counts = np.zeros(w.n + 1, np.int64)
    for d in range(1, w.n + 1):
        i = np.arange(w.n - d + 1)
        j = i + d
        best, cut, counts[d] = leftmost_best(cost, i, j, split[i, j - 1], np.minimum(split[i + 1, j], j - 1))
        cost[i, j], split[i, j] = best + w.w(i, j), cut
    return Solution(cost, split, counts)


def banded_costs(w: Weights, width: int) -> np.ndarray | None:
    """cost[d, i] of every cell (i, i + d) with d <= ``width``, by the windowed program, or None if one number can't hold a cost and a place.

    Costs of one size lie side by side, so neighbouring cells read and write neighbouring places. A candidate is a cost
    above the bits of its place among those of its diagonal: the least one is the leftmost best.
    """
    size, width = w.n + 1, min(width, w.n)
    bits = (2 * size).bit_length()
    if (int(w.p[-1]) + int(w.q[-1])) * (width.bit_length() + 2) << bits >= 1 << 63:
        return None
    cost, count = np.empty((width + 1, size), np.int64), np.arange(2 * size)
    flat, up_to, before = cost.ravel(), (w.p + w.q) << bits, (w.p + w.q - w.miss) << bits
    cost[0] = w.miss << bits
    # Place p of a diagonal has, in its cell t, the cut first - t + p: the cell's part of the left operand's index is fixed.
    cell_at, steps, cuts = count[:size] * (1 - 2 * size), count * size, count[:size]
    for d in range(1, width + 1):
        m = size - d
        if d == 1:
            value, cuts = cost[0, :m] + cost[0, 1:], count[:m]
        else:
            start, first = cuts + count[: m + 1], int(cuts[0])
            start -= first
            places = count[: int(start[m])]
            left = np.repeat(cell_at[:m] + first * size, start[1:] - start[:m])
            left += steps[: len(places)]
            # The operands' indices add up to the place and a number of the diagonal.
            right = places - left
            right += (d - 1) * size + first + 1
            sums = flat.take(left)
            sums += flat.take(right)
            sums += places
            value = np.minimum.reduceat(sums, start[:m])
            cuts = value & ((1 << bits) - 1)
            value -= cuts
            cuts += first
            cuts -= count[:m]
        value += up_to[d:]
        np.subtract(value, before[:m], out=cost[d, :m])
    cost >>= bits
    return cost


def solve_interval(n: int, merge, base) -> tuple[np.ndarray, np.ndarray]:  # noqa: ANN001
    """General interval program: cost(i, j) = min over i <= k < j of cost(i, k) + cost(k+1, j) + merge(i, k, j)."""
    cost, split = np.full((n, n), UNSET, np.int64), np.full((n, n), -1, np.int32)
    for i in range(n):
        cost[i, i], split[i, i] = base(i), i
    for d in range(1, n):
        for i in range(n - d):
            values = [int(cost[i, k] + cost[k + 1, i + d]) + merge(i, k, i + d) for k in range(i, i + d)]
            cost[i, i + d] = min(values)
            split[i, i + d] = i + values.index(min(values))
    return cost, split


def build_tree(split: np.ndarray, lo: int = 0, hi: int | None = None) -> list[tuple[int, int, int, int, str, int]]:
    """(rank, lo, hi, depth, side, parent rank; 0 for the root) of each node, top down from a cut table."""
    hi = split.shape[0] - 1 if hi is None else hi
    out, stack = [], [(lo, hi, 1, "root", 0)]
    while stack:
        a, b, depth, side, parent = stack.pop()
        if a == b:
            continue
        k = int(split[a, b])
        out.append((k + 1, a, b, depth, side, parent))
        stack += [(k + 1, b, depth + 1, "right", k + 1), (a, k, depth + 1, "left", k + 1)]
    return out


def depths_of(roots, n: int) -> tuple[np.ndarray, np.ndarray]:  # noqa: ANN001
    """Depths of keys 1..n and gaps 0..n of the tree whose root over (lo, hi) is key ``roots(lo, hi) + 1``."""
    keys, gaps, stack = np.zeros(n + 1, np.int64), np.zeros(n + 1, np.int64), [(0, n, 1)]
    while stack:
        a, b, depth = stack.pop()
        if a == b:
            gaps[a] = depth
            continue
        k = roots(a, b)
        keys[k + 1] = depth
        stack += [(a, k, depth + 1), (k + 1, b, depth + 1)]
    return keys, gaps


def tree_cost(w: Weights, keys: np.ndarray, gaps: np.ndarray, leaf_depth: str = "own") -> int:
    """Sum of depth times weight over keys and gaps; ``parent`` counts comparisons only for gaps."""
    return int((keys * w.hit).sum() + ((gaps - (leaf_depth == "parent")) * w.miss).sum())


def heuristic_roots(w: Weights, kind: str):  # noqa: ANN201
    """Root choices of the baselines: balanced, left or right chain, heaviest key, weight-balanced."""
    if kind == "balanced":
        return lambda a, b: (a + b - 1) // 2
    if kind == "chain_left":
        return lambda a, b: a
    if kind == "chain_right":
        return lambda a, b: b - 1
    if kind == "heaviest":
        return lambda a, b: a + int(np.argmax(w.hit[a + 1 : b + 1]))
    if kind == "weight_balanced":
        def middle(a: int, b: int) -> int:
            k = np.arange(a, b)
            left, right = w.w(np.full(len(k), a), k), w.w(k + 1, np.full(len(k), b))
            return a + int(np.argmin(np.abs(left - right)))
        return middle
    raise ValueError(kind)


def brute_force(w: Weights) -> list[tuple[int, int]]:
    """(root, cost) of every search tree (as many as the Catalan number; n up to 9)."""
    if w.n > 9:
        raise ValueError("enumeration is for at most nine keys")

    def trees(a: int, b: int) -> list[tuple[int, int]]:
        if a == b:
            return [(0, int(w.miss[a]))]
        own = int(w.w(np.array(a), np.array(b)))
        return [(k + 1, l + r + own) for k in range(a, b) for _, l in trees(a, k) for _, r in trees(k + 1, b)]

    return trees(0, w.n)
