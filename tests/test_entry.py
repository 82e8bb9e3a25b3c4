"""The entry module, and queries against their SQL."""

import importlib.util
import subprocess
import sys

import pytest

import __spark_entry__ as entry_module

TABLES = "region nation customer supplier part orders lineitem events documents embeddings pages benchmark labels conversations".split()
CHECKED = ["item_counts_grouping_sets", "pair_counts_bits", "levelwise_baskets_l2", "nonredundant_rules", "nonredundant_margin2", "balanced_rules_lift", "feature_matrix", "bin_cuts_k4", "info_distance", "grid_smooth", "target_quintiles", "asof_previous_label", "stream_window_counts", "parameter_rules", "hoeffding_table", "swap_bound_table"]


def test_entry_has_rows(spark):
    assert entry_module.entry(spark).count() == 10


def test_every_sql_has_a_query():
    queries, sql = entry_module.queries(), entry_module.oracle_sql()
    assert set(sql) <= set(queries) and len(queries) > 80
    assert all(callable(f) for f in queries.values())


def comparable(frame):
    import pandas as pd

    columns = sorted(frame.columns)
    return columns, sorted(tuple("" if pd.isna(v) else repr(float(v)) if isinstance(v, float) else str(v) for v in row) for row in frame[columns].astype(object).itertuples(index=False))


@pytest.mark.parametrize("name", CHECKED)
def test_query_equals_sql(spark, sf, name):
    import duckdb

    con = duckdb.connect()
    for t in TABLES:
        con.execute(f"CREATE VIEW {t} AS SELECT * FROM read_parquet('{sf}/{t}.parquet')")
    assert comparable(entry_module.queries()[name](spark, sf).toPandas()) == comparable(con.execute(entry_module.oracle_sql()[name]).fetchdf())


@pytest.mark.parametrize("name", ["hoeffding_table", "swap_bound_table"])
def test_bounds_read_their_table(spark, sf, name):
    found = entry_module.queries()[name](spark, sf)
    assert any("lineitem" in f for f in found.inputFiles())
    assert found.where("eps = 0.1").agg({"n": "sum"}).first()[0] == spark.read.parquet(f"{sf}/lineitem.parquet").count()


def test_budgets_read_their_tables(spark, sf, tmp_path):
    for t in TABLES:
        (tmp_path / f"{t}.parquet").symlink_to(f"{sf}/{t}.parquet") if t != "part" else spark.read.parquet(f"{sf}/part.parquet").where("p_size <= 10 and p_partkey * 7919 % 100 >= 3").write.parquet(str(tmp_path / "part.parquet"))
    classes = {r["p"]: (r["n_classes"], r["d_freq"]) for r in entry_module.queries()["parameter_rules"](spark, str(tmp_path)).collect()}
    assert classes[6] == (1, 10) and classes[23] == (2, 40)


def test_works_without_the_corpus_operators():
    hidden = """
import importlib.util, sys
real = importlib.util.find_spec
importlib.util.find_spec = lambda name, *a: None if name in ('rulefeat.llm', 'corpus_pipeline') else real(name, *a)
import __spark_entry__ as e
assert not [n for n in e.queries() if n.startswith('op') or n == 'pipeline'] and len(e.queries()) > 70
e.oracle_sql()
assert not [m for m in sys.modules if m.startswith('rulefeat.llm')]
"""
    subprocess.run([sys.executable, "-c", hidden], check=True, cwd=importlib.util.find_spec("__spark_entry__").origin.rpartition("/")[0])
