"""Tables with more keys than one task solves: blocks, the tree through them, and measures by units, against the kernel."""

import numpy as np
import pytest

from optbst.functions.kernel import Weights, build_tree, depths_of, solve_windowed
from optbst.operators import dynamic
from optbst.operators.trees import depths_of_nodes, program_depths
from optbst.plans import engine


@pytest.fixture()
def small_blocks(monkeypatch):
    """Tables of more than 20 keys are large, with blocks of 8 rows and strips of two."""
    monkeypatch.setattr(dynamic, "WHOLE", 20)
    monkeypatch.setattr(engine.workers, "__defaults__", (8,))
    monkeypatch.setattr(engine, "STRIP_BYTES", 12 * 16)


def made(spark, n, seed=5):
    r = np.random.default_rng(seed)
    w = Weights(np.where(r.random(n + 1) < 0.1, 900, r.integers(0, 9, n + 1)), r.integers(0, 5, n + 1))
    rows = [(i, int(h), int(m)) for i, (h, m) in enumerate(zip(w.hit, w.miss))]
    return w, spark.createDataFrame(rows, "idx long, hit long, miss long")


@pytest.mark.parametrize("values", [[[5, 5, 9]], [[1], [2]], [[0, 300, 70_000], [1, 1, 1 << 40]], [[9, 3, 4], [1 << 50, 0, 0]]])
def test_packed_matrices(values):
    assert engine.opened_matrix(engine.packed(np.array(values)), len(values)).tolist() == values


def test_many_keys_in_blocks(spark, small_blocks):
    w, table = made(spark, 61)
    want = solve_windowed(w)
    program = dynamic.Program(table)
    assert program.large and len(program.blocks().plan) > 20
    got = program.cells().toPandas()
    assert len(got) == 62 * 63 // 2
    assert (want.cost[got["lo"], got["hi"]] == got["cost"]).all() and (want.split[got["lo"], got["hi"]] == got["split"]).all()
    assert program.optimum().first()[0] == want.optimum
    nodes = program.nodes()
    assert sorted(zip(nodes["cut"] + 1, nodes["lo"], nodes["hi"], nodes["depth"], nodes["side"], nodes["parent"])) == sorted(build_tree(want.split))
    keys, gaps = depths_of(lambda a, b: int(want.split[a, b]), w.n)
    own = depths_of_nodes(nodes, w.n)
    assert (own[0] == keys).all() and (own[1] == gaps).all()
    depths = program_depths(program).toPandas().sort_values("idx")
    assert depths["gap_depth"].tolist() == gaps.tolist()


@pytest.mark.parametrize(("n", "hits", "scale"), [(61, 9, 1), (40, 1, 1), (47, 2, 1), (61, 9, 1 << 47)])
def test_units_of_the_windowed_program(monkeypatch, n, hits, scale):
    """Every unit by one number a candidate, as by cost and cut apart: ties, zero weights, and weights too large for one number."""
    r = np.random.default_rng(n)
    w = Weights(np.where(r.random(n + 1) < 0.1, 90, r.integers(0, hits, n + 1)) * scale, r.integers(0, 4, n + 1) * scale)
    want, used = solve_windowed(w), []
    own = engine.eval_windowed
    monkeypatch.setattr(engine, "eval_windowed", lambda *a: (used.append(1), own(*a))[1])
    units, total = [u for step in engine.schedule(n, engine.workers(n, 8), 0, "regular", "barrier") for u in step], 0
    for at, u in enumerate(units):
        low, high = (u.r0, u.c1 - 1) if u.c0 <= u.r1 else (int(want.split[u.r0, u.c0 - 1]), int(want.split[u.r1 + 1, u.c1]))
        slices = [(x.side, x.r0, x.c0, (want.split if "cut" in x.side else want.cost)[x.r0 : x.r1 + 1, x.c0 : x.c1 + 1].astype(np.int64)) for v in units[:at] for x in engine.needs(0, u, low, high, v)]
        cost, split, candidates = engine.eval_part(w, u, low, high, slices)
        assert (split == want.split[u.r0 : u.r1 + 1, u.c0 : u.c1 + 1]).all()
        assert (cost == want.cost[u.r0 : u.r1 + 1, u.c0 : u.c1 + 1])[split >= 0].all()
        total += candidates
    assert total == want.candidates.sum() and len(used) == (len(units) if scale == 1 else 0)


@pytest.mark.parametrize(("technique", "n", "p", "k"), [("regular", 50, 6, 0), ("irregular", 50, 4, 2), ("four_split", 50, 6, 1), ("four_split", 61, 4, 3), ("four_split", 13, 6, 2)])
@pytest.mark.parametrize("pruned", [True, False])
def test_units_of_every_technique(technique, n, p, k, pruned):
    """Units of unequal sides, with cuts bounded by their corners or not."""
    r = np.random.default_rng(n)
    w = Weights(r.integers(0, 9, n + 1), r.integers(0, 4, n + 1))
    want, before = solve_windowed(w), []
    for step in engine.schedule(n, p, k, technique, "dataflow"):
        for u in step:
            low, high = u.r0, u.c1 - 1
            if pruned and u.c0 > u.r1:
                low, high = int(want.split[u.r0, u.c0 - 1]), min(high, int(want.split[u.r1 + 1, u.c1]))
            slices = [(x.side, x.r0, x.c0, (want.split if "cut" in x.side else want.cost)[x.r0 : x.r1 + 1, x.c0 : x.c1 + 1].astype(np.int64)) for v in before for x in engine.needs(0, u, low, high, v)]
            cost, split, _ = engine.eval_part(w, u, low, high, slices)
            assert (split == want.split[u.r0 : u.r1 + 1, u.c0 : u.c1 + 1]).all()
            assert (cost == want.cost[u.r0 : u.r1 + 1, u.c0 : u.c1 + 1])[split >= 0].all()
        before += step


def test_units_are_measured_by_strips(spark, small_blocks, monkeypatch):
    monkeypatch.setattr(engine, "MEASURED_ROWS", 3)
    _, table = made(spark, 61)

    def measure(lo, hi, cut, left, below):
        import pandas as pd

        return pd.DataFrame({"rows": [len(set(lo))], "cells": [len(lo)]})

    got = engine.by_units(spark, dynamic.Program(table).blocks(), measure, "rows int, cells int").toPandas()
    assert got["rows"].max() == 3 and got["cells"].sum() == 61 * 62 // 2


def test_cuts_beside_units(spark, small_blocks):
    w, table = made(spark, 61)
    split = solve_windowed(w).split

    def measure(lo, hi, cut, left, below):
        import pandas as pd

        return pd.DataFrame({"lo": lo, "hi": hi, "cut": cut, "left": left, "below": below})

    got = engine.by_units(spark, dynamic.Program(table).blocks(), measure, "lo int, hi int, cut int, left int, below int").toPandas()
    assert len(got) == 61 * 62 // 2
    assert (split[got["lo"], got["hi"]] == got["cut"]).all() and (split[got["lo"], got["hi"] - 1] == got["left"]).all() and (split[got["lo"] + 1, got["hi"]] == got["below"]).all()


@pytest.mark.parametrize("name", ["optimal_cost_all", "saving_balanced", "heuristic_costs", "candidate_profile", "monotonicity", "tree_users", "depth_hist", "windowed_users", "udf_depth"])
def test_queries_over_blocks(spark, monkeypatch, name):
    import __spark_entry__

    run = __spark_entry__.queries()[name]
    want = sorted(run(spark, "/root/testdata/sf0.001").collect(), key=str)
    monkeypatch.setattr(dynamic, "WHOLE", 3)
    monkeypatch.setattr(engine.workers, "__defaults__", (8,))
    assert sorted(run(spark, "/root/testdata/sf0.001").collect(), key=str) == want


@pytest.mark.parametrize("name", ["windowed_supp", "replay_supp", "replay_users", "depth_quantiles"])
def test_more_queries_over_blocks(spark, monkeypatch, name):
    test_queries_over_blocks(spark, monkeypatch, name)


def test_units_do_not_hold_slices_twice():
    """What a unit has read of others is let go as it is placed, not kept beside the operands."""
    r = np.random.default_rng(4)
    w = Weights(r.integers(0, 9, 62), r.integers(0, 4, 62))
    want = solve_windowed(w)
    units = [u for step in engine.schedule(61, engine.workers(61, 8), 0, "regular", "barrier") for u in step]
    u = units[-1]
    low, high = int(want.split[u.r0, u.c0 - 1]), int(want.split[u.r1 + 1, u.c1])
    slices = [(x.side, x.r0, x.c0, (want.split if "cut" in x.side else want.cost)[x.r0 : x.r1 + 1, x.c0 : x.c1 + 1].astype(np.int64)) for v in units[:-1] for x in engine.needs(0, u, low, high, v)]
    assert len(slices) > 2
    engine.eval_part(w, u, low, high, slices)
    assert not slices


def test_cells_of_a_strip_take_little_memory():
    """Cells are handed on as they are opened: a task holds little more than one strip's cells, however many strips a batch has."""
    import tracemalloc

    import pyarrow as pa

    values = np.cumsum(np.ones((100, 1000), np.int64), 1)
    rows = [(100 * x, 100 * x + 99, 5000, 5999, engine.packed(values), engine.packed(values)) for x in range(6)]
    batch = pa.RecordBatch.from_arrays([pa.array(c) for c in zip(*rows)], names=["r0", "r1", "c0", "c1", "cost", "split"])
    tracemalloc.start()
    cells = sum(b.num_rows for b in engine._unpacker(iter([batch])))
    peak = tracemalloc.get_traced_memory()[1]
    tracemalloc.stop()
    assert cells == 600_000 and peak < 3 * 20 * 100_000


def test_large_groups_in_blocks(spark, small_blocks):
    r = np.random.default_rng(2)
    rows = [(g, k, int(r.integers(1, 50))) for g, n in (("a", 45), ("b", 3), (None, 30)) for k in range(n)]
    got = {x["grp"]: (x["n"], x["cost"]) for x in dynamic.solved_groups(spark.createDataFrame(rows, "g string, key int, hit long"), "g").collect()}
    want = {}
    for g in ("a", "b", None):
        own = [h for x, _, h in rows if x == g]
        want[str(g)] = (len(own), solve_windowed(Weights([0, *own], [0] * (len(own) + 1))).optimum)
    assert got == want


@pytest.mark.parametrize("values", [[[5, 5, 9, 12], [1, 2, 3, 90]], [[0, 300, 70_000], [1, 1, 1 << 40]], [[9, 3, 4], [1 << 50, 0, 0]], [[7], [8]]])
def test_slices_are_cut_out_of_packed_matrices(values):
    """Every rectangle of a packed matrix, as from the opened one."""
    data, own = engine.packed(np.array(values)), np.array(values)
    for r0, r1 in ((0, 0), (0, 1), (1, 1)):
        for c0 in range(own.shape[1]):
            for c1 in range(c0, own.shape[1]):
                assert engine.opened_matrix(engine.cut_out(data, 2, r0, r1, c0, c1), r1 - r0 + 1).tolist() == own[r0 : r1 + 1, c0 : c1 + 1].tolist()


@pytest.mark.parametrize(("technique", "k"), [("regular", 0), ("irregular", 1), ("four_split", 1)])
def test_units_read_no_tables_of_cuts(spark, monkeypatch, technique, k):
    """The cuts beside a unit come from the driver, which has them; only costs are read of other units."""
    w, _ = made(spark, 61)
    sides, own = set(), engine._cutter
    monkeypatch.setattr(engine, "_cutter", lambda plan: (sides.update(x.side for found in plan.values() for x in found), own(plan))[1])
    got = engine.unpacked(engine.solve(spark, w, 6, k, technique, "dataflow").state).toPandas()
    assert sides == {"left", "below"}
    want = solve_windowed(w)
    assert len(got) == 62 * 63 // 2
    assert (want.cost[got["lo"], got["hi"]] == got["cost"]).all() and (want.split[got["lo"], got["hi"]] == got["split"]).all()


def test_candidates_of_a_diagonal_are_numbered_once(monkeypatch):
    """Operands to the left and below are found by one index: a diagonal repeats one array by its windows, not two."""
    r = np.random.default_rng(4)
    w = Weights(r.integers(0, 9, 62), r.integers(0, 4, 62))
    repeated, repeat = [], np.repeat
    unit = engine.schedule(61, 1, 0, "regular", "barrier")[0][0]
    monkeypatch.setattr(engine.np, "repeat", lambda *a: (repeated.append(1), repeat(*a))[1])
    engine.eval_windowed(w, unit, unit.r0, unit.c1 - 1, [])
    assert 0 < len(repeated) <= unit.c1 - unit.r0


def test_weights_of_depths_come_from_the_trees_table(spark):
    """``depth_hist`` takes the hits that the tree was made from; it counts the events no second time."""
    import __spark_entry__

    assert not [f for f in __spark_entry__.queries()["depth_hist"](spark, "/root/testdata/sf0.001").inputFiles() if "events" in f]
