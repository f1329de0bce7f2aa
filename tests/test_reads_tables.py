"""Queries that made their rows up read a given table: Spark's scans are in their plans or jobs."""

import pytest
from pyspark.sql import functions as F

from tests.oracle import duck, same
from tidegate import registry
from tidegate.functions.scalar import normal_tail, z_for_tail
from tidegate.sources import tables

SF = "/root/testdata/sf0.01"
READS = {
    "a10_model_sizes": "embeddings", "b4_barrier_forecast": "events", "b4_elastic_barrier": "events", "b7_crash": "events", "g10_cut_for_tail": "lineitem", "g11_param_check": "lineitem",
    "g9_normal_tail": "lineitem", "r10_inline_fixtures": "events", "r97_recursive_sql": "lineitem", "r9_rate_source": "events", "x13_fleet_spread": "orders",
}


@pytest.mark.parametrize("name", sorted(READS))
def test_reads_its_table(spark, monkeypatch, name):
    loaded, load, stream = [], tables.load, tables.events_stream
    seen = lambda s, sf, table, *a, **b: (loaded.append(table), load(s, sf, table, *a, **b))[1]
    monkeypatch.setattr(tables, "load", seen)
    monkeypatch.setattr("tidegate.plans.suite_relational.load", seen)
    monkeypatch.setattr(tables, "events_stream", lambda *a, **b: (loaded.append("events"), stream(*a, **b))[1])
    df = registry.queries()[name](spark, SF)
    assert READS[name] in loaded
    same(df, SF, registry.oracle_sql()[name])
    assert len(duck(SF, registry.oracle_sql()[name]))


def test_published_shares(spark):
    """The published shares at three cuts, in percent, and the cuts for them."""
    rows = spark.createDataFrame([(-0.9, 18.406, 3), (-1.3, 9.68, 2), (-1.6, 5.48, 2)], "z double, pct double, digits int")
    for r in rows.select("*", (100 * normal_tail(F.col("z"))).alias("p"), z_for_tail(F.col("pct") / 100).alias("back")).collect():
        assert round(r["p"], r["digits"]) == r["pct"] and round(r["back"], 3) == r["z"]
