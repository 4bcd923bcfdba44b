"""Workers that have no copy of the package: what operators ship must open without it."""

import subprocess
import sys
import textwrap
from pathlib import Path

ROOT = Path(__file__).resolve().parents[2]


def test_operators_without_the_package_on_workers(tmp_path):
    code = textwrap.dedent(f"""
        import sys
        sys.path.insert(0, {str(ROOT)!r})
        from pyspark.sql import SparkSession
        spark = SparkSession.builder.master("local[2]").config("spark.sql.shuffle.partitions", "2").config("spark.ui.enabled", "false").getOrCreate()
        import public_tokenizers as P
        from optbst.functions.kernel import Weights, solve_windowed
        from optbst.llm import context_tree, decontaminate, packing, quality, toxicity
        from optbst.plans.engine import solve_blocks, unpacked
        text = " ".join("abc"[i % 3] + str(i % 7) for i in range(60))
        docs = spark.createDataFrame([(i, text + str(i)) for i in range(40)], "doc_id long, text string")
        labels = spark.createDataFrame([(i, i % 2, (i + 1) % 2) for i in range(40)], "doc_id long, quality int, toxic int")
        bench = spark.createDataFrame([(1, text)], "item_id long, text string")
        assert context_tree.language_model_scores(docs, depth=3).count() == 40
        assert decontaminate.contamination(docs, bench).where("contaminated").count() == 40
        assert packing.best_fit_packing(docs, P.path("word_bpe_49k.json")).count() == 40
        assert quality.quality_scores(docs, labels).count() == toxicity.toxicity_scores(docs, labels).count() == 40
        assert unpacked(solve_blocks(spark, Weights([0, 3, 1, 7], [0] * 4), 2, 1)).count() == 10
        print("all opened")
    """)
    # The driver's path is set in the program, so workers do not inherit it.
    got = subprocess.run([sys.executable, "-c", code], cwd=tmp_path, capture_output=True, text=True, timeout=600)
    assert "all opened" in got.stdout, got.stderr[-3000:]
