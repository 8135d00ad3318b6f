"""Queries against their SQL on the smallest tables, and the driver's contract."""

import os
import subprocess
import sys
from pathlib import Path

import pytest
from harness import compare

import __spark_entry__ as entry
from blockbwt.plans.catalogue import QUERIES, SQL

SF = "/root/testdata/sf0.001"
QUICK = [k for k in SQL if k.startswith(("rel_", "measure_", "published_", "size_table", "bucket_", "suffix_"))]
#: One of each kind that takes longer; the driver compares all.
SOME = ["bwt_worked_example", "bwt_reads_blocksort", "bwt_customer_names", "bwt_part_names", "range_plan_reads", "node_plan_reads", "lcp_urls", "lf_mapping_names", "locate_patterns_reads", "irreducible_overlaps", "io_fasta_roundtrip", "io_fastq", "io_node_ranges", "stream_session", "stream_incremental_index", "udf_udtf_kmers"]


@pytest.mark.parametrize("name", QUICK + SOME)
def test_query_equals_sql(spark, name):
    assert compare(spark, QUERIES[name], SQL[name], SF) == ""


def test_entry(spark):
    df = entry.entry(spark)
    assert df.columns == ["bwt_pos", "sid", "pos", "sym"]


def test_every_sql_has_a_query():
    assert set(entry.oracle_sql()) <= set(entry.queries())


def test_without_the_pipeline_operators(tmp_path):
    """The rest imports where they're deleted, and no session is needed for that."""
    import shutil

    root = Path(__file__).parent.parent
    shutil.copytree(root / "blockbwt", tmp_path / "blockbwt", ignore=shutil.ignore_patterns("llm", "__pycache__"))
    shutil.copy(root / "__spark_entry__.py", tmp_path)
    code = "import __spark_entry__ as e; q = e.queries(); assert q and not any(k.startswith('op') for k in q)"
    done = subprocess.run([sys.executable, "-c", code], cwd=tmp_path, capture_output=True, text=True, env={"PATH": "/usr/bin:/bin", "PYTHONPATH": str(tmp_path)})
    assert done.returncode == 0, done.stderr[-500:]
    # and the other tests are found and run there
    shutil.copytree(root / "tests", tmp_path / "tests", ignore=shutil.ignore_patterns("llm", "__pycache__"))
    shutil.copy(root / "bench.py", tmp_path)
    some = "test_plans or test_measures or test_every_sql_has_a_query"
    for extra in (["--collect-only"], ["-k", some]):
        done = subprocess.run([sys.executable, "-m", "pytest", "tests", "-q", "-p", "no:cacheprovider", *extra], cwd=tmp_path, capture_output=True, text=True, env={**os.environ, "PYTHONPATH": str(tmp_path)})
        assert done.returncode == 0, done.stdout[-500:]
