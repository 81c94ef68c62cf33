"""Registered queries against DuckDB on the smallest tables: one of each family."""

import duckdb
import numpy as np
import pandas as pd
import pytest

SF = "/root/testdata/sf0.001"
TABLES = "region nation customer supplier part orders lineitem events documents embeddings pages benchmark labels conversations".split()


def plain(x):
    if x is None or x is pd.NaT or str(x) in ("nan", "NaT", "<NA>", "None"):
        return None
    if isinstance(x, bool | np.bool_):
        return int(x)
    if isinstance(x, int | float | np.integer | np.floating):
        return round(float(x), 9)
    return str(x)[:10] if "date" in type(x).__name__ or "Time" in type(x).__name__ else str(x)


def rows(frame):
    columns = sorted(frame.columns)
    return columns, sorted((tuple(map(plain, r)) for r in zip(*[frame[c].tolist() for c in columns], strict=True)), key=repr)


@pytest.fixture(scope="session")
def duck():
    c = duckdb.connect()
    for t in TABLES:
        c.sql(f"CREATE VIEW {t} AS FROM '{SF}/{t}.parquet'")
    return c


def cases():
    from incrank.operators import blocks, ranks, relational
    from incrank.streaming import events

    some = [n for n in ranks.oracle_sql() if n.endswith("_event_flow") or n.endswith("pruned_geo_tree") or n.startswith("variant_")]
    return [(ranks, n) for n in some] + [(m, n) for m in (blocks, relational, events) for n in m.oracle_sql()]


@pytest.mark.parametrize("module,name", cases(), ids=lambda x: x if isinstance(x, str) else "")
def test_query(spark, duck, module, name):
    got, want = module.queries()[name](spark, SF).toPandas(), duck.sql(module.oracle_sql()[name]).df()
    assert rows(got) == rows(want)


def test_every_query_is_named_once_and_has_its_oracle():
    import __spark_entry__ as e

    assert set(e.oracle_sql()) <= set(e.queries())


def test_scaling_table_reads_its_table(spark):
    from incrank.operators.blocks import a_scaling_table

    assert a_scaling_table(spark, SF).inputFiles()


def test_approximate_aggregates(spark):
    from incrank.operators.relational import agg_approx
    from incrank.sources.workloads import cust_supp
    from pyspark.sql import functions as F

    exact = cust_supp(spark, SF).groupBy("src").agg(F.count_distinct("dst").alias("exact"))
    far = agg_approx(spark, SF).join(exact, "src").where("abs(targets - exact) > greatest(2, 0.2 * exact)")
    assert far.count() == 0


def test_asof_versions_at_the_start_only(spark, tmp_path):
    """The last version goes on to every later partition, however many there are."""
    from incrank.operators.relational import join_asof

    kinds = pd.Series(["signup"] * 10 + ["view"] * 3990)
    at = pd.Timestamp("2024-01-01") + pd.to_timedelta(range(4000), unit="min")
    spark.createDataFrame(pd.DataFrame({"event_id": range(4000), "ts": at, "event_type": kinds})).write.parquet(f"{tmp_path}/events.parquet")
    was = spark.conf.get("spark.sql.shuffle.partitions")
    spark.conf.set("spark.sql.shuffle.partitions", "200")
    try:
        got = {r["event_id"]: r["version"] for r in join_asof(spark, str(tmp_path)).collect()}
    finally:
        spark.conf.set("spark.sql.shuffle.partitions", was)
    assert got == {k: min(k, 9) for k in range(4000)}
