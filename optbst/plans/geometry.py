"""Partitions of the triangular table into blocks, their mapping, dependencies and schedule.

All in integers on the driver: a plan has a few thousand rows whatever the number of keys.
"""

from __future__ import annotations

from dataclasses import dataclass
from math import isqrt

PARTS = ("LL", "LU", "RL", "RU")


@dataclass(frozen=True)
class Block:
    """Rows r0..r1 and columns c0..c1, evaluated in round ``round`` at fragmentation level ``level``."""

    block_id: int
    round: int
    level: int
    r0: int
    r1: int
    c0: int
    c1: int

    @property
    def triangular(self) -> bool:
        return self.c0 <= self.r1

    @property
    def cells(self) -> int:
        rows, columns = self.r1 - self.r0 + 1, self.c1 - self.c0 + 1
        return rows * (rows + 1) // 2 if self.triangular else rows * columns


@dataclass(frozen=True)
class Part:
    """A sub-block (or a whole block, part ``all``)."""

    part_id: int
    block_id: int
    round: int
    part: str
    r0: int
    r1: int
    c0: int
    c1: int


def grid_side(p: int) -> int:
    """Smallest f with f * f >= 2p."""
    f = isqrt(2 * p)
    return f if f * f == 2 * p else f + 1


def block_side(n: int, p: int, level: int = 0) -> int:
    theta = -(-(n + 1) // grid_side(p))
    return -(-theta // (1 << level))


def cut_points(n: int, p: int, level: int) -> list[tuple[int, int]]:
    """The (half-open) intervals of 0..n at a level; those beyond n are empty and stay as place holders."""
    f, size = grid_side(p), n + 1
    own = [(min(a * block_side(n, p), size), min((a + 1) * block_side(n, p), size)) for a in range(f)]
    for l in range(1, level + 1):
        half = block_side(n, p, l)
        own = [x for a, b in own for x in ((a, min(a + half, b)), (min(a + half, b), b))]
    return own


def blocks(n: int, p: int, k: int = 0) -> list[Block]:
    """Irregular partition: diagonals from the one with half as many blocks as the first on are quartered, k times.

    k = 0 is the regular partition. Empty blocks (more intervals than rows) are left out.
    """
    f, out, done = grid_side(p), [], 0
    h = -(-f // 2)

    def add(number: int, level: int, a: int, b: int) -> None:
        cuts = cut_points(n, p, level)
        (r0, r1), (c0, c1) = cuts[a], cuts[b]
        if r1 > r0 and c1 > c0:
            out.append(Block(len(out), number, level, r0, r1 - 1, c0, c1 - 1))

    # A tail is the triangle of blocks (a, b) with b - a >= first, of 2^level * f intervals.
    first, size, level = 0, f, 0
    while True:
        keep = size - first - (h if level < k else 0)
        if level == 0:
            for d in range(keep):
                done += 1
                for a in range(size - d):
                    add(done, 0, a, a + d)
            first = keep
        else:
            # Quarters of the tail blocks: the fine diagonal t holds row and column halves with equal sum.
            rounds: dict[int, list[tuple[int, int]]] = {}
            for a in range(size):
                for b in range(size):
                    if b // 2 - a // 2 >= first // 2:
                        rounds.setdefault(b - a, []).append((a, b))
            order = sorted(rounds)
            if level < k:
                order = [t for t in order if size - t > h]
            for t in order:
                done += 1
                for a, b in sorted(rounds[t]):
                    add(done, level, a, b)
            first = (order[-1] + 1) if order else first
        if level == k:
            return out
        level, size, first = level + 1, 2 * size, 2 * first


def num_rounds(p: int, k: int) -> int:
    f = grid_side(p)
    return f + k * (-(-f // 2) + 1)


def parts(n: int, p: int, k: int, technique: str = "four_split") -> list[Part]:
    """The units of evaluation: whole blocks, quarters of blocks below level k, or blocks of level-k side."""
    out: list[Part] = []
    for b in blocks(n, p, k if technique != "regular" else 0):
        depth = {"four_split": min(1, k - b.level), "small_block": k - b.level}.get(technique, 0)
        for name, r0, r1, c0, c1 in _split(n, p, b, depth):
            out.append(Part(len(out), b.block_id, b.round, name, r0, r1, c0, c1))
    return out


def _split(n: int, p: int, b: Block, depth: int) -> list[tuple[str, int, int, int, int]]:
    if depth <= 0:
        return [("all", b.r0, b.r1, b.c0, b.c1)]
    cuts = [x for x in cut_points(n, p, b.level + depth) if x[1] > x[0]]
    rows = [x for x in cuts if b.r0 <= x[0] and x[1] - 1 <= b.r1]
    columns = [x for x in cuts if b.c0 <= x[0] and x[1] - 1 <= b.c1]
    out = []
    for ci, (c0, c1) in enumerate(columns):
        for ri, (r0, r1) in sorted(enumerate(rows), reverse=True):
            if c1 - 1 >= r0:
                name = ("L" if ci == 0 and len(columns) > 1 else "R") + ("U" if ri == 0 else "L") if depth == 1 else f"{ri}.{ci}"
                out.append((name, r0, r1 - 1, c0, c1 - 1))
    return out


def owners(plan: list[Block], p: int) -> dict[int, int]:
    """Cyclic deal of blocks to workers in the order of rounds, upper left to lower right."""
    return {b.block_id: number % p for number, b in enumerate(sorted(plan, key=lambda b: (b.round, b.r0)))}


def depends(x: Part | Block, y: Part | Block) -> bool:
    """Whether x reads cells of y: same rows further left, or same columns further down."""
    if (x.r0, x.c0) == (y.r0, y.c0) and (x.r1, x.c1) == (y.r1, y.c1):
        return False
    rows = y.r0 <= x.r1 and x.r0 <= y.r1 and y.c0 <= x.c1
    columns = y.c0 <= x.c1 and x.c0 <= y.c1 and y.r1 >= x.r0
    left, below = rows and y.c1 <= x.c1 and y.c0 <= x.c0, columns and y.r0 >= x.r0 and y.r1 >= x.r1
    return left or below


def waves(units: list[Part]) -> dict[int, int]:
    """The wave of each part: one after the last part that it depends on."""
    by_place = sorted(units, key=lambda u: (u.c0 - u.r1, u.c1 - u.r0, u.r0))
    wave: dict[int, int] = {}
    for u in by_place:
        wave[u.part_id] = 1 + max((wave[v.part_id] for v in by_place if v.part_id in wave and depends(u, v)), default=0)
    return wave


def phases(units: list[Part]) -> list[list[Part]]:
    """Barrier order: LL of all blocks of a round, then LU, RL and RU; whole blocks in one phase."""
    key = lambda u: (u.round, {"LU": 1, "RL": 2, "RU": 3}.get(u.part, 0))
    out: dict[tuple[int, int], list[Part]] = {}
    for u in units:
        out.setdefault(key(u), []).append(u)
    return [out[k] for k in sorted(out)]


def step_messages(n: int, p: int, k: int) -> list[tuple[int, int, str, int]]:
    """(block, step, pair of parts, consuming worker) of the four-split schedule."""
    plan = blocks(n, p, k)
    own = owners(plan, p)
    out = set()
    for b in plan:
        if b.level == k:
            pairs = [(4, "all", b.r0, b.r1, "rows"), (4, "all", b.c0, b.c1, "columns")]
        else:
            cuts = [x for x in cut_points(n, p, b.level + 1) if x[1] > x[0]]
            rows, columns = [x for x in cuts if b.r0 <= x[0] <= b.r1], [x for x in cuts if b.c0 <= x[0] <= b.c1]
            pairs = [(2, "LL+LU", *_ends(columns[0]), "columns"), (3, "LL+RL", *_ends(rows[-1]), "rows"), (4, "RL+RU", *_ends(columns[-1]), "columns"), (5, "LU+RU", *_ends(rows[0]), "rows")]
        for step, names, a, z, side in pairs:
            for x in plan:
                if x.round > b.round and (x.r0 <= z and a <= x.r1 and x.c0 > b.c1 if side == "rows" else x.c0 <= z and a <= x.c1 and x.r1 < b.r0) and own[x.block_id] != own[b.block_id]:
                    out.add((b.block_id, step, names, own[x.block_id]))
    return sorted(out)


def _ends(x: tuple[int, int]) -> tuple[int, int]:
    return x[0], x[1] - 1


def comm_rounds(p: int, k: int) -> int:
    """The number of communication rounds by the published formula (k >= 1)."""
    s = grid_side(p)
    return 3 + 4 * (s // 2 - 1) + 4 * (k - 1) * (-(-s // 2) + 1) + s + s % 2


def theory_time(n: int, p: int, k: int, added_term: bool = True) -> float:
    """Bound on one worker's computation in cells; ``added_term`` keeps a sum that the list of steps lacks (k >= 1)."""
    s = grid_side(p)
    h = -(-s // 2) + 1
    total = (3 + 4 * (s // 2 - 1)) / (4 * p) + sum(4 * h / (4**level * p) for level in range(2, k + 1))
    return n * n * (total + (h * added_term + s + s % 2) / (4**k * p))
