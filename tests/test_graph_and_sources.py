"""The dynamic graph, sources and sinks, special weights, and the SQL definitions of plans."""

import duckdb
import numpy as np
import pytest

from optbst.functions.kernel import Weights, build_tree, depths_of, solve_cubic, solve_windowed
from optbst.operators.dynamic import cells_frame, solved, solved_groups
from optbst.operators.graph import REDUCED, arcs_into, dual_arcs, duality_in_tiles, graph_vertices, path_to_tree, shortest_paths
from optbst.operators.weights import collected, prefix, weight_table
from optbst.plans import geometry as g
from optbst.plans import in_sql
from optbst.sources import synthetic
from optbst.sources.files import read_weights, register_views, write_tree, write_weights


@pytest.fixture(scope="module")
def table(spark):
    """Three keys with hits 3, 1, 7 and misses 2, 0, 1, 4."""
    return spark.createDataFrame([(0, None, 0, 2), (1, "a", 3, 0), (2, "b", 1, 1), (3, "c", 7, 4)], "idx long, key string, hit long, miss long")


def test_graph_of_three_keys(spark, table):
    w, pre = Weights([0, 3, 1, 7], [2, 0, 1, 4]), prefix(table)
    s, cells = solve_cubic(w), solved(table)
    assert graph_vertices(spark, 3).count() == 11
    arcs = arcs_into(cells, pre)
    kinds = {r["kind"]: r["count"] for r in arcs.groupBy("kind").count().collect()}
    # 18 distinct arcs, 14 of them in the reduced graph.
    assert kinds == {"source": 4, "right": 6, "up": 6, "across": 4, "above": 4}
    assert len({(r["a"], r["b"], r["i"], r["j"]) for r in arcs.collect()}) == 18 and sum(kinds[k] for k in REDUCED) == 14
    both = dual_arcs(arcs, cells).collect()
    assert len(both) == 4 and all(r["along"] == r["dual"] >= s.cost[r["i"], r["j"]] for r in both)
    for reduced in (False, True):
        assert all(r["cost"] == s.cost[r["lo"], r["hi"]] for r in shortest_paths(pre, 3, reduced).collect())
    want = {(r, lo, hi, depth) for r, lo, hi, depth, _, _ in build_tree(s.split)}
    assert {tuple(r) for r in path_to_tree(arcs, cells, 3).collect()} == want


@pytest.mark.parametrize("tile", [4, 7, 64])
def test_duality_in_tiles(spark, tile):
    r = np.random.default_rng(3)
    w = Weights(r.integers(0, 9, 24), r.integers(0, 5, 24))
    cells = cells_frame(solve_windowed(w))
    run = lambda own: tuple(duality_in_tiles(spark.createDataFrame(own), w, tile).first())
    jumps = sum(j - i - 1 for i in range(24) for j in range(i + 1, 24))
    assert run(cells) == (jumps, 0, 0)
    # A wrong cost of (9, 9) is another value than that of the unit arc into every (i, 9), and one of (0, 23) is above its jumps.
    wrong = cells.assign(cost=cells["cost"] + 1000 * ((cells["lo"] == 9) & (cells["hi"] == 9)))
    assert run(wrong)[:2] == (jumps, 8)
    high = cells.assign(cost=cells["cost"] + 10**6 * ((cells["lo"] == 0) & (cells["hi"] == 23)))
    assert run(high) == (jumps, 0, 22)


def test_duality_of_many_keys(spark, monkeypatch):
    import __spark_entry__
    from optbst import catalogue_graph

    run = __spark_entry__.queries()["duality_nation"]
    want = run(spark, "/root/testdata/sf0.001").collect()
    monkeypatch.setattr(catalogue_graph, "_ARC_KEYS", 3)
    assert run(spark, "/root/testdata/sf0.001").collect() == want


def test_a_wrong_weight_breaks_the_duality(spark, table):
    from pyspark.sql import functions as F

    cells = solved(table)
    arcs = arcs_into(cells, prefix(table))
    wrong = arcs.withColumn("weight", F.col("weight") + F.when(F.col("kind") == "above", 1).otherwise(0))
    assert sum(r["along"] != r["dual"] for r in dual_arcs(wrong, cells).collect()) == 1


@pytest.mark.parametrize("a", [(31, 4, 2), (17, 32, 3), (40, 5, 3), (0, 4, 1), (513, 8, 0)])
def test_plans_in_sql(a):
    assert sorted(duckdb.sql(in_sql.blocks_sql(*a)).fetchall()) == sorted(tuple(vars(b).values()) for b in g.blocks(*a))
    assert sorted(duckdb.sql(in_sql.parts_sql(*a)).fetchall()) == sorted(tuple(vars(b).values()) for b in g.parts(*a))


@pytest.mark.parametrize("law", ["uniform", "zipf", "all_hit", "all_miss"])
def test_synthetic_source(spark, law):
    synthetic.register(spark)
    w = collected(spark.read.format("synthetic_weights").option("n", 40).option("law", law).load())
    assert w.n == 40 and (law != "all_hit" or not w.miss.any()) and (law != "all_miss" or not w.hit.any())
    a, b = solve_cubic(w), solve_windowed(w)
    assert (a.cost == b.cost).all() and (a.split == b.split).all()
    assert spark.read.format("synthetic_weights").option("n", 0).load().count() == 1


@pytest.mark.parametrize("kind", ["csv", "json"])
def test_weights_to_files_and_back(spark, table, tmp_path, kind):
    path = str(tmp_path / kind)
    write_weights(table, path, kind)
    assert sorted(map(tuple, read_weights(spark, path, kind).collect()), key=str) == sorted(map(tuple, table.collect()), key=str)


def test_malformed_rows(spark, tmp_path):
    (tmp_path / "w.csv").write_text("idx,key,hit,miss\n0,,0,2\n1,a,three,0\n2,b,1,1\n")
    path = str(tmp_path / "w.csv")
    assert len(read_weights(spark, path, malformed="DROPMALFORMED").collect()) == 2  # a count alone parses no column
    assert [r["hit"] for r in read_weights(spark, path, malformed="PERMISSIVE").orderBy("idx").collect()] == [0, None, 1]
    with pytest.raises(Exception):
        read_weights(spark, path).collect()


def test_trees_to_files_and_views(spark, tmp_path):
    nodes = spark.createDataFrame([(2, "b", 1, 0, "root"), (1, "a", 2, 2, "left"), (3, "c", 2, 2, "right")], "rank long, key string, depth int, parent_rank long, side string")
    for kind in ("parquet", "csv", "json"):
        write_tree(nodes, str(tmp_path / kind), kind)
    assert spark.read.parquet(str(tmp_path / "parquet")).count() == 3
    root = spark.read.json(str(tmp_path / "json")).where("rank = 2").first()
    assert [c["key"] for c in root["children"]] == ["a", "c"]
    register_views(spark, nodes_of_tree=nodes)
    assert spark.sql("SELECT count(*) FROM nodes_of_tree WHERE depth = 2").first()[0] == 2


def test_special_weights(spark):
    """No keys, one key, keys that nothing looks up, and probes that all miss."""
    probes = spark.createDataFrame([(1, 4), (5, 2)], "key int, n long")
    none = spark.createDataFrame([], "key int")
    w = collected(weight_table(none, probes))
    assert w.n == 0 and w.miss.tolist() == [6] and solve_windowed(w).optimum == 6
    w = collected(weight_table(spark.createDataFrame([(3,)], "key int"), probes))
    assert w.hit.tolist() == [0, 0] and w.miss.tolist() == [4, 2] and solve_windowed(w).optimum == 12
    w = collected(weight_table(spark.createDataFrame([(1,), (5,), (9,)], "key int"), probes))
    assert w.hit.tolist() == [0, 4, 2, 0] and not w.miss.any()
    zero = solve_windowed(Weights(np.zeros(5, int), np.zeros(5, int)))
    assert zero.optimum == 0 and zero.split[0, 4] == 0


def test_eleven_letters():
    """A hand-made tree over eleven letters: the root at depth 1, the letter h at depth 5, one more for a miss below it."""
    letters = "cefghklnors"
    roots = {(0, 11): "n", (0, 7): "f", (0, 2): "c", (1, 2): "e", (3, 7): "l", (3, 6): "g", (4, 6): "h", (5, 6): "k", (8, 11): "r", (8, 9): "o", (10, 11): "s"}
    keys, gaps = depths_of(lambda a, b: letters.index(roots[a, b]), 11)
    assert keys[letters.index("n") + 1] == 1 and keys[letters.index("h") + 1] == 5 and sorted(keys[1:]) == [1, 2, 2, 3, 3, 3, 3, 4, 4, 5, 6]
    assert gaps[letters.index("h")] == 6 and len(gaps) == 12


def test_many_small_groups(spark):
    rng = np.random.default_rng(4)
    data = [(f"g{i % 60}" if i % 61 else None, int(k), int(h)) for i, (k, h) in enumerate(zip(rng.permutation(900), rng.integers(0, 9, 900)))]
    got = {r["grp"]: (r["n"], r["cost"]) for r in solved_groups(spark.createDataFrame(data, "grp string, key int, hit long"), "grp").collect()}
    for name in {d[0] for d in data}:
        hits = [h for grp, _, h in sorted(data, key=lambda d: d[1]) if grp == name]
        assert got[str(name)] == (len(hits), solve_cubic(Weights([0, *hits], [0] * (len(hits) + 1))).optimum)


@pytest.mark.parametrize("n,side", [(0, 4), (13, 4), (30, 7)])
def test_progressive_blocks(spark, n, side):
    from optbst.plans.progressive import middle_blocks, solve_progressive

    rng = np.random.default_rng(n)
    w = Weights(rng.integers(0, 4, n + 1), rng.integers(0, 4, n + 1))
    s = solve_windowed(w)
    got = solve_progressive(spark, w, side).collect()
    assert len(got) == (n + 1) * (n + 2) // 2 and all((r["cost"], r["split"]) == (s.cost[r["lo"], r["hi"]], s.split[r["lo"], r["hi"]]) for r in got)
    # Every block between the ends is taken in once, from half-way diagonals on.
    assert sorted(k for s_ in range(20) for k in middle_blocks(2, 11, s_)) == list(range(3, 11)) and min(s_ for s_ in range(20) if middle_blocks(2, 11, s_)) == 5
