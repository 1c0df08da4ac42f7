"""The entry module: its queries against their SQL, and without the optional parts."""

import collections
import math
import os
import shutil
import subprocess
import sys

import duckdb
import pytest

import __spark_entry__ as entry

ROOT = os.path.dirname(os.path.dirname(os.path.abspath(__file__)))
SOME = (
    "find_hits_events online_sift_events online_sift_interval_touching kernel_engine_blocks bank_mixed_k offline_greedy free_start_intervals hits_qgram_index coverage_by_position decision_delay hit_count_table "
    "w1_hit_counts w14_updown_patterns example_sift_shortest asof_last_event fuzzy_join_parts occ_grouping_sets rank_occ_per_stream moving_hit_rate udtf_scan sql_recursive_count hits_session hits_sliding occ_extremes occ_cube w3_lp_sweep w12_conversations sift_one_stream_blocks find_hits_wavefront motif_map resource_linear_fit"
).split()


def plain(value):
    if isinstance(value, float):
        return "nan" if math.isnan(value) else round(value, 6)
    if isinstance(value, (list, tuple)):
        return tuple(map(plain, value))
    return value


def same(spark, tables, name):
    con = duckdb.connect()
    for file in os.listdir(tables):
        con.execute(f"CREATE VIEW {file.removesuffix('.parquet')} AS SELECT * FROM '{tables}/{file}'")
    df = entry.queries()[name](spark, tables)
    columns = sorted(df.columns)
    result = con.sql(entry.oracle_sql()[name])
    assert sorted(result.columns) == columns
    got = collections.Counter(plain(tuple(r)) for r in df.select(*[f"`{c}`" for c in columns]).collect())
    quoted = ", ".join('"' + c + '"' for c in columns)
    assert got == collections.Counter(plain(r) for r in con.sql(f"SELECT {quoted} FROM result").fetchall())


@pytest.mark.parametrize("name", SOME)
def test_query_against_sql(spark, tables, name):
    same(spark, tables, name)


def test_entry_and_names(spark):
    assert entry.entry(spark).count() > 0
    assert set(entry.oracle_sql()) <= set(entry.queries())


def test_without_optional_parts(tmp_path):
    shutil.copytree(ROOT, tmp_path / "repo", ignore=shutil.ignore_patterns(".git", "llm", "corpus_pipeline.py", "__pycache__", "spark-warehouse"))
    code = "import __spark_entry__ as e; q = e.queries(); assert 'online_sift_events' in q and not any(n.startswith('op') and n[2].isdigit() for n in q) and 'pipeline' not in q and set(e.oracle_sql()) <= set(q)"
    subprocess.run([sys.executable, "-B", "-c", code], cwd=tmp_path / "repo", check=True, env={k: v for k, v in os.environ.items() if k != "PYTHONPATH"})
    # the other tests are found, and those without a session run
    shutil.rmtree(tmp_path / "repo" / "tests" / "llm", ignore_errors=True)
    some = [sys.executable, "-B", "-m", "pytest", "-q", "-p", "no:cacheprovider", "tests", "-k", "kernels_agree or many_islands or pieces_equal or bank_in_one"]
    assert " passed" in subprocess.run(some, cwd=tmp_path / "repo", check=True, capture_output=True, text=True).stdout
