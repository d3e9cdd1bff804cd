"""Plans of the main operators, and the entry module."""

import subprocess
import sys
from pathlib import Path

import pytest

from veilwalk.operators import degree
from veilwalk.plans import oracles, queries
from veilwalk.sources import graphs

REPO = Path(__file__).resolve().parents[1]


def plan(df):
    return df._jdf.queryExecution().executedPlan().toString()


def test_scans_are_pruned(spark, sf):
    text = plan(graphs.copurchase(spark, sf))
    assert "ReadSchema: struct<l_orderkey:bigint,l_partkey:bigint>" in text
    assert "Cartesian" not in text and "BatchEvalPython" not in text


def test_no_single_task_windows(spark, sf):
    for df in (graphs.document_terms(spark, sf), graphs.buys_from(spark, sf), degree.ordered_matrices(*_edges_and_vectors(spark))):
        assert "SinglePartition" not in plan(df)


def _edges_and_vectors(spark):
    return spark.createDataFrame([(1, 2), (2, 1)], "v long, u long"), spark.createDataFrame([(1, [1.0]), (2, [1.0])], "v long, c array<double>")


def test_every_oracle_has_a_query():
    assert set(oracles.SQL) <= set(queries.queries())


@pytest.mark.parametrize("left", ["nothing", "pipeline", "llm"])
def test_entry_works_without_training_data_part(tmp_path, left):
    """Without both parts, and with one of them left behind, the rest imports and knows only its own queries."""
    import shutil

    for name in ("veilwalk", "__spark_entry__.py", "corpus_pipeline.py"):
        src = REPO / name
        if src.exists():
            (shutil.copytree if src.is_dir() else shutil.copy)(src, tmp_path / name)
    if left != "llm":
        shutil.rmtree(tmp_path / "veilwalk" / "llm", ignore_errors=True)
    if left != "pipeline":
        (tmp_path / "corpus_pipeline.py").unlink(missing_ok=True)
    code = "import __spark_entry__ as e; q = e.queries(); assert q and not any(n.startswith('op') or n == 'pipeline' for n in q); assert set(e.oracle_sql()) <= set(q)"
    subprocess.run([sys.executable, "-c", code], cwd=tmp_path, check=True, env={"PATH": "/usr/bin:/bin", "PYTHONPATH": str(tmp_path)})
