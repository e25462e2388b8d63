"""Every query with SQL gives the SQL's rows on the smallest tables."""

from __future__ import annotations

import pytest

from arrayfactor import registry

SMALL = "/root/testdata/sf0.001"


@pytest.mark.parametrize("key", sorted(registry.ORACLES))
def test_query_equals_sql(spark, duck, same, key):
    same(registry.QUERIES[key](spark, SMALL).toPandas(), duck.sql(registry.ORACLES[key]).df())


def test_entry_point_registers_everything():
    import __spark_entry__ as entry_point

    assert set(registry.QUERIES) <= set(entry_point.queries())
    assert set(entry_point.oracle_sql()) <= set(entry_point.queries())


def test_coordinate_source_round_trip(spark, tmp_path):
    from arrayfactor.sources import coo

    coo.register(spark)
    rows = [(1, 2, 3, 1.0), (4, 5, 6, 0.25)]
    spark.createDataFrame(rows, "i1 long, i2 long, i3 long, y double").write.format("coo").option("modes", 3).mode("append").save(str(tmp_path / "a"))
    assert sorted(map(tuple, spark.read.format("coo").option("modes", 3).load(str(tmp_path / "a")).collect())) == rows
    assert sorted(map(tuple, coo.read_coordinates(spark, str(tmp_path / "a"), 3).collect())) == rows


# queries that once made up their data, with the table that they read now
READ = {
    "udtf_plan": "events",
    "decay_closed_form": "events",
    "scaling_curve": "lineitem",
    "kron_small": "lineitem",
    "vec_identity": "lineitem",
    "merge_mean": "events",
    "merge_touched": "events",
    "merge_laplace": "events",
    "udaf_vec_mean": "events",
    "budget_table": "events",
    "cost_model": "lineitem",
    "traffic_model": "events",
}


@pytest.mark.parametrize("key", sorted(READ))
def test_query_reads_its_table(spark, key):
    files = registry.QUERIES[key](spark, SMALL).inputFiles()
    assert any(f.endswith(f"/{READ[key]}.parquet") for f in files)


def test_table_function_draws_from_the_log(spark):
    rows = registry.QUERIES["udtf_plan"](spark, SMALL).collect()
    users = spark.read.parquet(f"{SMALL}/events.parquet").select("user_id").distinct().count()
    assert len(rows) == len(set(rows)) == 4 * 3 * 5 and 0 < max(r.idx for r in rows if r.mode == 1) <= users
    assert {r.idx for r in rows if r.mode == 2} == {1, 2, 3, 4, 5}
