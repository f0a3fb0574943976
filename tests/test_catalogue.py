"""Registered queries against DuckDB on the smallest tables, where those are there."""

from __future__ import annotations

import os
import shutil
import subprocess
import sys
from pathlib import Path

import pytest

import __spark_entry__ as entry
from nearfield import catalogue

SF = "/root/testdata/sf0.001"
SOME = ("bf_nn_orders2", "exact_nn_orders2", "exact_nn_part2", "oneshot_nn_cust2", "exact_rules_ring", "cover_exact_sizes", "agg_cube_work", "join_asof_events", "win_list_prefix", "sql_exact_search", "stream_tumbling_nn", "exact_measured_orders2", "cover_delete", "approx_nn_line4", "pivots_farthest", "containment_7gamma")

#: Queries that once made their rows up.
ON_TABLES = ("expansion_rate_grid", "oneshot_params", "planner_choice", "predicted_costs", "scan_pointset")


def test_every_oracle_has_a_query():
    assert set(catalogue.oracle_sql()) <= set(catalogue.queries())
    assert set(entry.oracle_sql()) <= set(entry.queries())


@pytest.mark.parametrize("with_pipeline", [True, False])
def test_entry_imports_without_the_corpus_subpackage(tmp_path, with_pipeline):
    root = Path(entry.__file__).parent
    shutil.copytree(root / "nearfield", tmp_path / "nearfield", ignore=shutil.ignore_patterns("llm", "__pycache__"))
    for name in ("__spark_entry__.py", *(["corpus_pipeline.py"] if with_pipeline else [])):
        if (root / name).exists():
            shutil.copy(root / name, tmp_path)
    told = subprocess.run([sys.executable, "-c", "import __spark_entry__ as e; print(sorted(e.queries()) == sorted(e.catalogue.queries()))"], cwd=tmp_path, capture_output=True, text=True, timeout=120)
    assert told.stdout.strip() == "True", told.stderr


@pytest.mark.skipif(not os.path.isdir(SF), reason="tables are not here")
@pytest.mark.parametrize("name", SOME + ON_TABLES)
def test_query_equals_its_sql(spark, name):
    import duckdb

    con = duckdb.connect()
    for t in ("region", "nation", "customer", "supplier", "part", "orders", "lineitem", "events", "documents", "embeddings", "pages", "benchmark"):
        con.sql(f"CREATE VIEW {t} AS SELECT * FROM '{SF}/{t}.parquet'")
    df = catalogue.queries()[name](spark, SF)
    rel = con.sql(catalogue.oracle_sql()[name])
    assert sorted(df.columns) == sorted(rel.columns)
    order = [rel.columns.index(c) for c in df.columns]
    plain = lambda row: tuple(round(v, 6) if isinstance(v, float) else v for v in row)
    want = sorted((plain([r[i] for i in order]) for r in rel.fetchall()), key=repr)
    assert sorted((plain(r) for r in df.collect()), key=repr) == want


@pytest.mark.skipif(not os.path.isdir(SF), reason="tables are not here")
@pytest.mark.parametrize("name", ON_TABLES)
def test_query_follows_its_table(spark, tmp_path, name):
    """Half of the rows of orders and lineitem give another answer: the query reads them."""
    for t in ("customer", "orders", "lineitem"):
        rows = spark.read.parquet(f"{SF}/{t}.parquet")
        rows.where(f"{rows.columns[0]} % 2 = 0").write.parquet(f"{tmp_path}/{t}.parquet")
    run = catalogue.queries()[name]
    assert sorted(map(repr, run(spark, SF).collect())) != sorted(map(repr, run(spark, str(tmp_path)).collect()))


@pytest.mark.skipif(not os.path.isdir(SF), reason="tables are not here")
def test_search_as_sql_ranks_no_pairs_by_a_window(spark):
    """Pairs of queries and pivots, or of queries and rows, are aggregated where they are made."""
    plan = catalogue.queries()["sql_exact_search"](spark, SF)._jdf.queryExecution().optimizedPlan().toString()
    assert "Aggregate" in plan and "Window" not in plan


@pytest.mark.skipif(not os.path.isdir(SF), reason="tables are not here")
def test_approximate_bound_takes_its_best_from_the_cover(spark, monkeypatch):
    """The best answers come from an exact search of the same cover: no table is scanned for all queries."""
    from nearfield.operators import bruteforce as bf

    monkeypatch.setattr(bf, "nearest", lambda *a, **b: pytest.fail("a scan of all rows"))
    found = catalogue.queries()["approx_nn_bound"](spark, SF).collect()
    assert found and all(r.within_ratio for r in found)
