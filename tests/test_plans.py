import shutil
import subprocess
import sys
from pathlib import Path

from winnow.operators import dedup, lm, metrics_table, select, similarity
from winnow.plans import catalog
from winnow.sources.tables import read_table

ROOT = Path(__file__).resolve().parents[1]


def plan(df, mode="formatted"):
    return df._sc._jvm.PythonSQLUtils.explainString(df._jdf.queryExecution(), mode)


def test_scans_prune_and_push_down(spark, sf):
    p = plan(catalog.queries()["op_scan_pruned"](spark, sf))
    assert "PushedFilters: [IsNotNull(l_shipdate)" in p and "l_comment" not in p


def test_scoring_joins_are_broadcast_and_texts_are_not_shuffled(spark, sf):
    docs = read_table(spark, sf, "documents")
    seed = read_table(spark, sf, "benchmark").withColumnRenamed("item_id", "seed_id")
    p = plan(metrics_table.score_all(docs, similarity.centroid(seed), lm.train(read_table(spark, sf, "conversations"))))
    assert "BroadcastHashJoin" in p and "CartesianProduct" not in p and "SortMergeJoin" not in p
    exchanges = [x for x in p.split("\n\n") if x.startswith("(") and ") Exchange" in x.split("\n")[0]]
    assert exchanges and all("text" not in x.split("Arguments")[0] for x in exchanges)


def test_exact_dedup_shuffles_digests_only(spark, sf):
    p = plan(dedup.exact(read_table(spark, sf, "documents")))
    exchanges = [x for x in p.split("\n\n") if ") Exchange" in x.split("\n")[0]]
    assert any("_ex_d" in x and "text" not in x for x in exchanges)


def test_the_cut_sorts_nothing_as_a_whole(spark, sf):
    m = metrics_table.standard(spark, sf)
    p = plan(select.hard(m, "entropy", select.budget(m, 0.1)))
    assert "CartesianProduct" not in p and "SinglePartition" not in p.split("Window")[0]
    windows = [x for x in p.split("\n\n") if ") Window" in x.split("\n")[0]]
    assert any("_rt_part" in x for x in windows)


def test_the_rest_works_without_the_llm_folders(tmp_path):
    """In a copy without the two folders and the pipeline, the entry lists the other queries, one of them runs and all other tests are collected."""
    gone = shutil.ignore_patterns("llm", "__pycache__", "corpus_pipeline.py", ".git", "*.md", "*.json", "*.txt")
    shutil.copytree(ROOT, tmp_path / "copy", ignore=gone)
    code = "import __spark_entry__ as e; from pyspark.sql import SparkSession as S; q = e.queries(); assert 'hard_entropy' in q and not any(n.startswith('op1_') or n == 'pipeline' for n in q); e.oracle_sql(); s = S.builder.master('local[2]').config('spark.ui.enabled', 'false').getOrCreate(); assert e.entry(s).count() > 0"
    ran = subprocess.run([sys.executable, "-c", code], cwd=tmp_path / "copy", capture_output=True, text=True)
    assert ran.returncode == 0, ran.stderr[-2000:]
    listed = subprocess.run([sys.executable, "-m", "pytest", "tests", "--collect-only", "-q"], cwd=tmp_path / "copy", capture_output=True, text=True)
    assert listed.returncode == 0 and "error" not in listed.stdout.lower().splitlines()[-1], listed.stdout[-2000:]


def test_nothing_else_imports_the_llm_folder():
    for f in (ROOT / "winnow").rglob("*.py"):
        if "llm" not in f.parts:
            assert "winnow.llm" not in f.read_text()


def test_entry(spark):
    import __spark_entry__

    assert __spark_entry__.entry(spark).count() > 0
    assert set(__spark_entry__.oracle_sql()) <= set(__spark_entry__.queries())
