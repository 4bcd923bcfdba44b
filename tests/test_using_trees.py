"""Lookups, replays, as-of joins and the progressive program against plain Python."""

from bisect import bisect_right

import numpy as np
import pytest

from optbst.functions.kernel import Weights, brute_force, depths_of, solve_windowed, tree_cost
from optbst.functions.sql import register
from optbst.operators.trees import as_of, lookup, replay_cost, solved_progressive, tree_depths
from optbst.operators.weights import prefix, weight_table
from optbst.plans import geometry as g


@pytest.mark.parametrize("n", [0, 1, 30])
def test_as_of(spark, n):
    r = np.random.default_rng(n)
    keys = sorted({int(x) for x in r.integers(0, 100, n)})
    probes = [(i, int(x)) for i, x in enumerate(r.integers(-5, 110, 80))] + [(80, None)]
    left = spark.createDataFrame(probes, "id int, key int")
    right = spark.createDataFrame([(k, i + 1) for i, k in enumerate(keys)], "key int, rank long")
    got = {x["id"]: x["rank"] for x in as_of(left, right, "key", "rank", 0).collect()}
    assert got == {i: 0 if k is None else bisect_right(keys, k) for i, k in probes}


def test_as_of_without_probes(spark):
    empty = spark.createDataFrame([], "id int, key int")
    assert as_of(empty, spark.createDataFrame([(1, 1)], "key int, rank long"), "key", "rank", 0).count() == 0


@pytest.mark.parametrize("kind", ["optimal", "balanced", "chain_left", "heaviest"])
def test_replay_is_the_tree_cost(spark, kind):
    counts = spark.createDataFrame([(k, 1 + k * 7 % 5) for k in range(40)], "key int, n long")
    table = weight_table(counts.where("key % 3 = 1").select("key"), counts)
    own = table.toPandas().sort_values("idx")
    w = Weights(own["hit"].to_numpy(), own["miss"].to_numpy())
    got = replay_cost(lookup(counts, table, tree_depths(table, kind))).first()
    assert got["probes"] == sum(1 + k * 7 % 5 for k in range(40))
    if kind == "optimal":
        assert got["cost"] == solve_windowed(w).optimum
    else:
        from optbst.functions.kernel import heuristic_roots

        assert got["cost"] == tree_cost(w, *depths_of(heuristic_roots(w, kind), w.n)) >= solve_windowed(w).optimum


def test_progressive_equals_windowed(spark):
    hit, miss = [0, 4, 0, 4, 9, 1, 1], [2, 0, 3, 3, 0, 5, 1]
    table = spark.createDataFrame([(i, h, m) for i, (h, m) in enumerate(zip(hit, miss))], "idx long, hit long, miss long")
    want = solve_windowed(Weights(np.array(hit), np.array(miss)))
    got = solved_progressive(table, prefix(table)).collect()
    assert len(got) == 28 and all((r["cost"], r["split"]) == (want.cost[r["lo"], r["hi"]], want.split[r["lo"], r["hi"]]) for r in got)


def test_functions_for_sql(spark):
    register(spark)
    assert [r[0] for r in spark.sql("SELECT grid_side(id) FROM range(1, 200)").collect()] == [g.grid_side(p) for p in range(1, 200)]
    assert spark.sql("SELECT * FROM partition_blocks(31, 4, 1)").count() == 15
    spark.createDataFrame([(1, 3), (2, 1), (3, 7), (None, 5)], "k int, n long").createOrReplaceTempView("hits_for_sql")
    assert spark.sql("SELECT optimal_cost(k, n) FROM hits_for_sql").first()[0] == min(c for _, c in brute_force(Weights([0, 3, 1, 7], [0] * 4)))


def test_theory_time_falls_with_k():
    times = [g.theory_time(40960, 32, k, False) for k in range(1, 6)]
    assert times == sorted(set(times), reverse=True)
