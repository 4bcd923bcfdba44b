"""Partitions of a given table's dictionary: their size follows the table."""

import pytest

import __spark_entry__


@pytest.fixture(scope="module")
def line_items(spark, tmp_path_factory):
    """Twelve days of the month, thirty quantities by flag, 34 buckets of parts, 500 orders."""
    d = str(tmp_path_factory.mktemp("tables"))
    own = spark.range(500).selectExpr("id AS l_orderkey", "id % 34 AS l_partkey", "cast(make_date(1996, 5, int(id % 12) + 1) AS timestamp_ntz) AS l_shipdate", "'A' AS l_returnflag", "double(id % 30 + 1) AS l_quantity")
    own.write.parquet(f"{d}/lineitem.parquet")
    return d


@pytest.mark.parametrize(("name", "n"), [("blocks_n31_p4_k1", 12), ("blocks_n150_p8_k2", 30), ("blocks_n4096_p32_k3", 500), ("blocks_n40960_p128_k2", 500)])
def test_blocks_of_a_table(spark, line_items, name, n):
    rows = __spark_entry__.queries()[name](spark, line_items).collect()
    assert max(r["c1"] for r in rows) == n and max(r["hits"] for r in rows) == 500
    assert sum((r["r1"] - r["r0"] + 1) * (r["c1"] - r["c0"] + 1) if r["c0"] > r["r1"] else (r["r1"] - r["r0"] + 1) * (r["r1"] - r["r0"] + 2) // 2 for r in rows) == (n + 1) * (n + 2) // 2


def test_plans_of_a_table(spark, line_items):
    from optbst.plans import geometry as g

    q = __spark_entry__.queries()
    assert {(r["block_id"], r["dep_block"]) for r in q["block_deps"](spark, line_items).collect()} == {(x.block_id, y.block_id) for x in g.blocks(12, 6, 1) for y in g.blocks(12, 6, 1) if g.depends(x, y)}
    assert sum(r["blocks"] for r in q["block_load"](spark, line_items).collect()) == len(g.blocks(12, 6, 1))
    assert q["block_deps_range"](spark, line_items).where("block_id >= dep_block").count() == sum(g.depends(x, y) for x in g.blocks(34, 5, 2) for y in g.blocks(34, 5, 2))
    assert sum(r["blocks"] for r in q["alg3_rounds"](spark, line_items).collect()) == len(g.blocks(500, 32, 2))


@pytest.mark.parametrize("name", ["blocks_n150_p8_k2", "blocks_n31_p4_k1", "blocks_n31_p4_k2", "blocks_n31_p8_k1", "blocks_n31_p8_k2", "blocks_n40960_p128_k2"])
def test_blocks_follow_the_table_as_in_sql(spark, line_items, name):
    import duckdb

    own = __spark_entry__.queries()[name](spark, line_items)
    assert own.inputFiles()
    db = duckdb.connect()
    db.execute(f"CREATE VIEW lineitem AS SELECT * FROM read_parquet('{line_items}/lineitem.parquet/*.parquet')")
    want = db.execute(__spark_entry__.oracle_sql()[name]).fetchall()
    assert sorted(map(tuple, own.collect())) == sorted(want)
