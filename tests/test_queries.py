"""Every workload against its SQL twin on the smallest tables, and what their plans must not hold."""

import math
import os
import subprocess
import sys

import duckdb
import pytest

import __spark_entry__ as entry
from tests.conftest import SF

TABLES = "region nation customer supplier part orders lineitem events documents embeddings pages benchmark labels conversations".split()
QUERIES, SQL = entry.queries(), entry.oracle_sql()
MINE = [n for n in QUERIES if n in SQL]


@pytest.fixture(scope="module")
def duck():
    con = duckdb.connect()
    for t in TABLES:
        con.sql(f"CREATE VIEW {t} AS SELECT * FROM '{SF}/{t}.parquet'")
    return con


def shown(v):
    if isinstance(v, float):
        return "nan" if math.isnan(v) else f"{v:.6f}" if v != int(v) else str(int(v))
    return str(v)


@pytest.mark.parametrize("name", MINE)
def test_query_equals_its_sql(spark, duck, name):
    df = QUERIES[name](spark, SF)
    columns = sorted(df.columns)
    got = sorted(tuple(shown(r[c]) for c in columns) for r in df.collect())
    want = duck.sql(SQL[name])
    assert sorted(want.columns) == columns
    at = [want.columns.index(c) for c in columns]
    assert got == sorted(tuple(shown(r[i]) for i in at) for r in want.fetchall())


@pytest.mark.parametrize("name", [n for n in QUERIES if n not in SQL and not n.startswith("op") and n != "pipeline"])
def test_query_without_sql_gives_rows(spark, name):
    assert QUERIES[name](spark, SF).count() > 0


def test_entry(spark):
    assert entry.entry(spark).count() > 0


@pytest.mark.parametrize("name", ["conj_pairs", "dnf_pairs", "cnf_pairs", "band_pairs_docs", "fast_sketch_blocks", "join_date_range", "asof_prior_report", "jaccard_exact_docs"])
def test_plans_hold_no_nested_loops(spark, name):
    plan = QUERIES[name](spark, SF)._jdf.queryExecution().executedPlan().toString()
    assert "CartesianProduct" not in plan and "BroadcastNestedLoopJoin" not in plan


def test_flagship_moves_only_keys(spark):
    plan = QUERIES["fast_sketch_blocks"](spark, SF)._jdf.queryExecution().executedPlan().toString()
    assert plan.count("Exchange hashpartitioning") == 1 and "Python" not in plan


def test_scan_prunes_and_pushes(spark):
    plan = QUERIES["scan_parquet"](spark, SF)._jdf.queryExecution().executedPlan().toString()
    assert "PushedFilters: [IsNotNull(lang), IsNotNull(n_chars), EqualTo(lang,en), GreaterThanOrEqual(n_chars,1000)]" in plan
    assert "text" not in plan.split("ReadSchema")[1]


@pytest.mark.parametrize("name", ["char_grams_toronto", "collision_curve", "key_similarity", "rule_space", *(f"letter_costs_{p}" for p in ("equal", "form", "keyboard", "phonetic"))])
def test_reads_a_given_table(spark, name):
    assert "FileScan parquet" in QUERIES[name](spark, SF)._jdf.queryExecution().executedPlan().toString()


def test_imports_without_the_training_data_part(tmp_path):
    root = os.path.dirname(os.path.dirname(os.path.abspath(__file__)))
    code = "import sys; sys.modules['linkblock.llm'] = None; sys.modules['corpus_pipeline'] = None; import __spark_entry__ as e; q = e.queries(); assert 'fast_sketch_blocks' in q and not any(n.startswith('op1') for n in q); e.oracle_sql()"
    subprocess.run([sys.executable, "-c", code], cwd=root, check=True)
