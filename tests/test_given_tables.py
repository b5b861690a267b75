"""Queries that once made up their rows: they read a given table, and equal their SQL, on shards and workers without rows too."""

import os
import shutil

import pytest

from posterior_mesh import registry

ALLOCATIONS = ["allocation_one_shot", "allocation_groups_5_2", "allocation_groups_40_2", "allocation_groups_40_4", "allocation_coded_5_2", "allocation_coded_40_4"]


@pytest.fixture(scope="session")
def few(spark, sf, tmp_path_factory):
    """The tables with a hundred line items of few orders and fifty events."""
    at = str(tmp_path_factory.mktemp("few"))
    for name in ("lineitem", "events"):
        spark.read.parquet(f"{sf}/{name}.parquet").where("l_orderkey < 20" if name == "lineitem" else "event_id % 20 = 0").coalesce(1).write.parquet(f"{at}/{name}.parquet.d")
        part = next(f for f in os.listdir(f"{at}/{name}.parquet.d") if f.endswith(".parquet"))
        shutil.copy(f"{at}/{name}.parquet.d/{part}", f"{at}/{name}.parquet")
    return at


def check(spark, folder, name, table):
    duckdb = pytest.importorskip("duckdb")
    got = registry.QUERIES[name](spark, folder)
    assert any(f.endswith(f"{table}.parquet") for f in got.inputFiles())
    with duckdb.connect() as db:
        db.execute(f"CREATE VIEW {table} AS SELECT * FROM '{folder}/{table}.parquet'")
        names = sorted(got.columns)
        want = db.execute(f"SELECT {', '.join(names)} FROM ({registry.ORACLES[name]})").fetchall()
    rows = [tuple(r) for r in got.select(names).collect()]
    assert rows and sorted(rows) == sorted(want)


@pytest.mark.parametrize("name", ALLOCATIONS)
def test_allocations_are_of_the_rows_of_lineitem(spark, sf, few, name):
    for folder in (sf, few):
        check(spark, folder, name, "lineitem")


@pytest.mark.parametrize("name", ["arrival_patterns_5_2", "arrival_patterns_40_2", "arrival_patterns_40_4", "clock_check", "crossover"])
def test_times_are_of_events(spark, sf, few, name):
    # of 40 workers, sf0.001 has too few users for a complete round
    for folder in ("/root/testdata/sf0.01",) if "_40_" in name else (sf, few):
        check(spark, folder, name, "events")
