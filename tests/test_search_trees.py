"""Kernels, geometry, engine and measures of the search-tree engine."""

from collections import Counter

import numpy as np
import pytest

from optbst.functions.kernel import Weights, banded_costs, brute_force, depths_of, heuristic_roots, solve_cubic, solve_windowed, tree_cost
from optbst.plans import geometry as g
from optbst.plans.published import runs
from optbst.plans.simulate import simulate, work_map


def random_weights(seed, n, high=9):
    r = np.random.default_rng(seed)
    return Weights(r.integers(0, high, n + 1), r.integers(0, high, n + 1))


def test_three_keys():
    w = Weights(np.array([0, 3, 1, 7]), np.zeros(4, int))
    assert sorted(c for _, c in brute_force(w)) == [16, 18, 20, 21, 26]
    s = solve_windowed(w)
    assert s.optimum == 16 and s.split[0, 3] == 2
    assert tree_cost(w, *depths_of(heuristic_roots(w, "balanced"), 3)) == 21


def test_five_keys_with_misses():
    s = solve_windowed(Weights(np.array([0, 15, 10, 5, 10, 20]), np.array([5, 10, 5, 5, 5, 10])))
    assert s.optimum == 275 and s.split[0, 5] == 1


@pytest.mark.parametrize("n", [0, 1, 2, 7, 40])
def test_solvers_agree(n):
    for seed in range(5):
        w = random_weights(seed, n, 3)
        a, b = solve_cubic(w), solve_windowed(w)
        assert (a.cost == b.cost).all() and (a.split == b.split).all()
        assert a.candidates.sum() == n * (n + 1) * (n + 2) // 6
        if n <= 7:
            assert min(c for _, c in brute_force(w)) == b.optimum
        assert tree_cost(w, *depths_of(lambda i, j: int(b.split[i, j]), n)) == b.optimum


def test_negative_and_too_large_weights():
    with pytest.raises(ValueError):
        Weights(np.array([0, -1]), np.array([0, 0]))
    with pytest.raises(OverflowError):
        Weights(np.array([0, 1 << 61]), np.array([1 << 60, 0]))


@pytest.mark.parametrize("p,k,blocks,subblocks,sizes", [(3, 1, 15, 21, [3, 2, 4, 3, 2, 1]), (4, 2, 24, 57, [3, 2, 4, 3, 2, 4, 3, 2, 1]), (5, 1, 19, 36, [4, 3, 2, 4, 3, 2, 1]), (8, 2, 28, 72, [4, 3, 2, 4, 3, 2, 4, 3, 2, 1])])
def test_counted_partitions(p, k, blocks, subblocks, sizes):
    plan = g.blocks(31, p, k)
    assert len(plan) == blocks and len(g.parts(31, p, k)) == subblocks
    assert [n for _, n in sorted(Counter(b.round for b in plan).items())] == sizes and len(sizes) == g.num_rounds(p, k)


def test_mapping_and_messages():
    plan = g.blocks(31, 6, 1)
    own = g.owners(plan, 6)
    assert Counter(own.values()) == {0: 4, 1: 3, 2: 3, 3: 3, 4: 3, 5: 3}
    block = next(b for b in plan if b.round == 2 and own[b.block_id] == 5)
    sent = {}
    for b, _, pair, to in g.step_messages(31, 6, 1):
        if b == block.block_id:
            sent.setdefault(pair, set()).add(to)
    assert sent == {"LL+LU": {1, 3}, "LL+RL": {0, 2}, "RL+RU": {1, 4}, "LU+RU": {3}}


@pytest.mark.parametrize("n,p,k", [(31, 4, 2), (5, 8, 1), (17, 32, 3), (40, 5, 3), (0, 4, 1)])
def test_every_cell_in_one_part(n, p, k):
    for t in ("regular", "irregular", "four_split", "small_block"):
        seen = np.zeros((n + 1, n + 1), int)
        for u in g.parts(n, p, k, t):
            seen[u.r0 : u.r1 + 1, u.c0 : u.c1 + 1] += 1
        assert (seen[np.triu_indices(n + 1)] == 1).all()


@pytest.mark.parametrize("technique,mode,pruned", [("regular", "barrier", True), ("irregular", "barrier", False), ("four_split", "dataflow", True), ("small_block", "dataflow", True)])
def test_block_engine(spark, technique, mode, pruned):
    from optbst.plans.engine import solve_blocks, unpacked

    w = random_weights(3, 23)
    s = solve_windowed(w)
    c = unpacked(solve_blocks(spark, w, 4, 1, technique, mode, pruned)).toPandas()
    assert len(c) == 24 * 25 // 2
    assert (s.cost[c.lo, c.hi] == c.cost).all() and (s.split[c.lo, c.hi] == c.split).all()


def test_published_order_and_simulated_order():
    times = {(t, n, p, k): s for plat, t, n, p, k, s in runs() if plat == "A"}
    for (t, n, p, k), s in times.items():
        if t == "irregular":
            assert times["four_split", n, p, k] < s < times["regular", n, p, 0]
    work = work_map(solve_windowed(random_weights(5, 300, 50)))
    for n in (300, 3000):
        for k in (1, 2):
            four, irr, reg = (simulate(work, n, 32, k, t, 0.0, 0.0).makespan for t in ("four_split", "irregular", "regular"))
            assert four < irr < reg


def test_weights_of_probes(spark):
    from optbst.operators.weights import collected, hit_counts, weight_table
    from pyspark.sql import functions as F

    probes = spark.createDataFrame([(x,) for x in [1, 5, 5, 7, 9, 9, 9, None, 20]], "k int")
    n = hit_counts(probes, F.col("k"))
    w = collected(weight_table(n.where("key IN (5, 9)").select("key"), n))
    assert w.hit.tolist() == [0, 2, 3] and w.miss.tolist() == [1, 1, 1]


def test_entry_without_text_operators(spark):
    import __spark_entry__ as e

    assert set(e.oracle_sql()) <= set(e.queries())
    assert "tree_users" in e.queries()


@pytest.mark.parametrize(("n", "high", "scale"), [(0, 9, 1), (1, 9, 1), (2, 2, 1), (61, 9, 1), (40, 2, 1), (90, 70, 1 << 30)])
@pytest.mark.parametrize("share", [1, 2, 5])
def test_costs_of_a_band(n, high, scale, share):
    """Every cell up to a width, as in the whole table."""
    own = random_weights(n, n, high)
    w, width = Weights(own.hit * scale, own.miss * scale), n // share
    want, got = solve_windowed(w).cost, banded_costs(w, width)
    assert got.shape == (width + 1, n + 1)
    for d in range(width + 1):
        i = np.arange(n + 1 - d)
        assert (got[d, i] == want[i, i + d]).all()


def test_groups_of_a_band():
    """Groups side by side cost what each costs alone, also where their hits are too large for one number."""
    from optbst.operators.dynamic import costs_of_groups

    r = np.random.default_rng(8)
    for most, sizes in ((9, (5, 1, 7, 7, 2)), (1 << 50, (6, 4)), (1 << 60, (2, 1, 1, 2)), (3, (1,))):
        groups = [r.integers(0, most, n) for n in sizes]
        assert costs_of_groups(groups) == [solve_windowed(Weights([0, *hits], [0] * (len(hits) + 1))).optimum for hits in groups]


def test_groups_of_similar_size_are_solved_together(monkeypatch, spark):
    """Hundreds of small groups of one partition take few programs, not one each."""
    from optbst.operators import dynamic

    rows = [(f"g{g}", k, 1 + (g * k) % 5) for g in range(300) for k in range(1 + g % 7)]
    mark = spark.sparkContext.accumulator(0)
    own = dynamic.costs_of_groups
    monkeypatch.setattr(dynamic, "costs_of_groups", lambda groups: (mark.add(1), own(groups))[1])
    got = {r["grp"]: (r["n"], r["cost"]) for r in dynamic.solved_groups(spark.createDataFrame(rows, "g string, key int, hit long").coalesce(1), "g").collect()}
    want = {f"g{g}": [1 + (g * k) % 5 for k in range(1 + g % 7)] for g in range(300)}
    assert got == {g: (len(h), solve_windowed(Weights([0, *h], [0] * (len(h) + 1))).optimum) for g, h in want.items()}
    assert 0 < mark.value <= 3 * int(spark.conf.get("spark.sql.shuffle.partitions"))
