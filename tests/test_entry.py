"""The entry point: every query with SQL gives the SQL's rows on the smallest tables, and only an absent subpackage passes."""

import glob
import importlib
import math
import os
import sys

import duckdb
import pytest

import __spark_entry__ as entry

SF = "/root/testdata/sf0.001"
QUICK = [
    "cuts_class4_order3", "two_level_bins", "trees_by_language", "best_partitions_ev5", "cluster_variants_ev5", "nestings_class4", "w5_packed_windows", "w6_counters", "adaptive_orders_reads",
    "sparse_updates_reads", "fitted_rates_users", "soft_objective_ev5", "decoded_reads", "long_machines", "prefix_rate_text42", "baseline_codes", "contingency_langs", "read_file_rates",
]


def plain(frame):
    cell = lambda x: None if x is None or isinstance(x, float) and math.isnan(x) else x if isinstance(x, str) else float(x)
    return sorted((tuple(map(cell, r)) for r in frame[sorted(frame.columns)].itertuples(index=False)), key=str)


@pytest.mark.parametrize("name", QUICK)
def test_same_rows_as_sql(spark, name):
    con = duckdb.connect()
    for f in glob.glob(f"{SF}/*.parquet"):
        con.execute(f"CREATE VIEW {os.path.basename(f)[:-8]} AS SELECT * FROM '{f}'")
    want, got = con.execute(entry.oracle_sql()[name]).df(), entry.queries()[name](spark, SF).toPandas()
    assert sorted(got.columns) == sorted(want.columns) and plain(got) == plain(want)


def test_half_lives_come_from_a_table(spark, tmp_path):
    texts = ["x" * 9, "y" * 8, "é" * 7, "ab", "c", "", None]
    spark.createDataFrame(list(enumerate(texts)), "doc_id long, text string").write.parquet(f"{tmp_path}/documents.parquet")
    got = entry.queries()["half_life_table"](spark, str(tmp_path)).toPandas()
    assert {(r.rate, r.docs) for r in got.itertuples()} == {(3, 2), (2, 1), (1, 1)} and got.half_life[got.rate == 1].tolist() == [1.0]
    con = duckdb.connect()
    con.execute(f"CREATE VIEW documents AS SELECT * FROM '{tmp_path}/documents.parquet/*.parquet'")
    assert plain(con.execute(entry.oracle_sql()["half_life_table"]).df()) == plain(got)


def test_sql_belongs_to_queries():
    assert set(entry.oracle_sql()) <= set(entry.queries())


def test_only_an_absent_subpackage_passes(monkeypatch):
    if not entry._llm()[0]:
        pytest.skip("the subpackage is not there")
    monkeypatch.setitem(sys.modules, "regex_that_is_not_there", None)
    monkeypatch.setitem(sys.modules, "corpus_pipeline", None)
    with pytest.raises(ImportError):
        importlib.import_module("corpus_pipeline")
    assert entry._llm() == ({}, {})
