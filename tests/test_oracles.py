"""Every query with SQL against DuckDB on the smallest tables, and plans and streams against their batch twins."""

import duckdb
import numpy as np
import pandas as pd
import pytest
from pyspark.sql import functions as F

from kernelblocks.queries import ORACLES, QUERIES

TABLES = "region nation customer supplier part orders lineitem events documents embeddings pages benchmark labels conversations".split()


@pytest.fixture(scope="module")
def duck(sf):
    con = duckdb.connect()
    con.execute("SET TimeZone = 'UTC'")
    for t in TABLES:
        con.execute(f"CREATE VIEW {t} AS SELECT * FROM '{sf}/{t}.parquet'")
    return con


def plain(df: pd.DataFrame) -> pd.DataFrame:
    df = df[sorted(df.columns)].copy()
    for c in df.columns:
        if pd.api.types.is_datetime64_any_dtype(df[c]):
            df[c] = df[c].astype("datetime64[us]")
        elif pd.api.types.is_numeric_dtype(df[c]) or df[c].map(lambda v: isinstance(v, (int, float)) or v is None or v is pd.NA).all():
            df[c] = pd.to_numeric(df[c], errors="coerce").astype(float)
        else:
            df[c] = df[c].map(lambda v: None if v is None or v is pd.NA else str(list(v)) if isinstance(v, (list, np.ndarray)) else v)
    return df.sort_values(list(df.columns), ignore_index=True)


@pytest.mark.parametrize("name", sorted(ORACLES))
def test_equals_duckdb(spark, sf, duck, name):
    got, want = plain(QUERIES[name](spark, sf).toPandas()), plain(duck.execute(ORACLES[name]).df())
    pd.testing.assert_frame_equal(got, want, check_dtype=False, atol=2e-6, rtol=1e-9)


def test_filters_and_columns_reach_the_scan(spark, sf):
    plan = QUERIES["filter_reduced"](spark, sf)._jdf.queryExecution().executedPlan().toString()
    assert "PushedFilters: [" in plan and "In(l_returnflag" in plan
    schema = plan.split("ReadSchema:")[1].split("\n")[0]
    assert "l_comment" not in schema and "l_tax" not in schema


def test_windows_over_a_stream_equal_the_table(spark, sf, tmp_path):
    from kernelblocks.streaming.windows import sessions, tumbling

    events = spark.read.parquet(f"{sf}/events.parquet")
    events.repartition(1).write.parquet(str(tmp_path / "in"))
    stream = spark.readStream.schema(events.schema).parquet(str(tmp_path / "in"))
    for name, f in (("tumbling", tumbling), ("sessions", sessions)):
        q = f(stream).writeStream.format("memory").queryName(f"kb_{name}").outputMode("complete" if name == "tumbling" else "append").trigger(availableNow=True).start()
        q.awaitTermination(120)
        got, batch = spark.table(f"kb_{name}"), f(events.withColumn("ts", F.col("ts").cast("timestamp")))
        if name == "tumbling":
            assert got.exceptAll(batch).isEmpty() and batch.exceptAll(got).isEmpty()
        else:
            assert got.count() > 0 and got.exceptAll(batch).isEmpty()


def test_scoring_and_standardizing_streams(spark, sf, tmp_path):
    from kernelblocks.baselines.ridge import feature_ridge
    from kernelblocks.functions.featuremaps import FourierMap
    from kernelblocks.operators.prep import embedding_task
    from kernelblocks.streaming.scoring import refresh, running_standardize, score_stream, with_customer, without_replays

    ex = embedding_task(spark.read.parquet(f"{sf}/embeddings.parquet"), "xor01")
    model = feature_ridge(ex, FourierMap(2, 32, 2, 1), 1e-3)
    ex.write.parquet(str(tmp_path / "ex"))
    stream = spark.readStream.schema(ex.schema).parquet(str(tmp_path / "ex"))
    q = score_stream(stream, model).writeStream.format("memory").queryName("kb_scored").trigger(availableNow=True).start()
    q.awaitTermination(120)
    assert spark.table("kb_scored").select("row_id", "pred").exceptAll(score_stream(ex, model).select("row_id", "pred")).isEmpty()
    events = spark.read.parquet(f"{sf}/events.parquet").select("event_id", "ts", "user_id", "value")
    events.repartition(1).write.parquet(str(tmp_path / "ev"))
    ev = spark.readStream.schema(events.schema).parquet(str(tmp_path / "ev"))
    spark.conf.set("spark.sql.streaming.stateStore.providerClass", "org.apache.spark.sql.execution.streaming.state.RocksDBStateStoreProvider")
    try:
        q = running_standardize(ev).writeStream.format("memory").queryName("kb_running").outputMode("append").trigger(availableNow=True).option("checkpointLocation", str(tmp_path / "cp")).start()
        q.awaitTermination(180)
    finally:
        spark.conf.unset("spark.sql.streaming.stateStore.providerClass")
    got = spark.table("kb_running").toPandas().set_index("event_id")["z"]
    want = {}
    for _, g in events.toPandas().sort_values(["ts", "event_id"]).groupby("user_id"):
        for k in range(len(g)):
            v = g["value"].to_numpy()[: k + 1]
            want[g["event_id"].iloc[k]] = (v[-1] - v.mean()) / v.std() if v.std() > 0 else 0.0
    assert np.allclose([got[k] for k in want], list(want.values()), atol=1e-6)
    assert without_replays(events.union(events), ["event_id"]).count() == events.count()
    assert with_customer(events, spark.read.parquet(f"{sf}/customer.parquet")).count() == events.count()
    q = refresh(stream, FourierMap(2, 32, 2, 1), str(tmp_path / "model"), rounds=2, rows=2).trigger(availableNow=True).option("checkpointLocation", str(tmp_path / "cp2")).start()
    q.awaitTermination(180)
    assert spark.read.parquet(str(tmp_path / "model/model/weights")).count() == 2


def test_sql_functions(spark, sf):
    from kernelblocks.baselines.ridge import feature_ridge
    from kernelblocks.functions.featuremaps import FourierMap
    from kernelblocks.functions.sqlfunctions import register, register_model, vector_sum
    from kernelblocks.operators.asof import range_join
    from kernelblocks.operators.prep import embedding_task, standardize

    register(spark)
    ex = embedding_task(spark.read.parquet(f"{sf}/embeddings.parquet"), "xor01")
    register_model(spark, feature_ridge(ex, FourierMap(2, 32, 2, 1), 1e-3))
    ex.createOrReplaceTempView("kb_ex")
    assert spark.sql("SELECT avg(cast((predict_margin(x) >= 0) = (label > 0) AS int)) FROM kb_ex").first()[0] > 0.8
    assert spark.sql("SELECT * FROM kb_feature_block(array(1D, 2D), 6, 1D, 3, 1, 2)").count() == 3
    total = ex.groupBy("label").agg(vector_sum("x").alias("s")).collect()
    assert all(len(r["s"]) == 2 for r in total)
    flat = standardize(spark.createDataFrame([(1.0,), (1.0,)], "v double"), ["v"]).collect()
    assert [r["v_z"] for r in flat] == [0.0, 0.0]
    times = spark.sql("SELECT 1 AS k, timestamp'2024-01-01 00:30:00' AS ts")
    spans = spark.sql("SELECT 1 AS k, timestamp'2024-01-01 00:00:00' AS a, timestamp'2024-01-01 05:00:00' AS b")
    assert range_join(times, spans, "k", "ts", "a", "b", 3600).count() == 1


def test_step_profile_and_scaling(spark):
    from kernelblocks.measures import scaling_table, step_profile, weak_table

    times = spark.createDataFrame([(0, "round", 10.0), (1, "round", 8.0), (0, "transform", 2.0), (1, "transform", 4.0)], "row_block int, step string, sec double")
    got = {r["step"]: r for r in step_profile(times).collect()}
    assert got["transform"]["share"] == 40.0 and got["round"]["avg_sec"] == 9.0
    runs = spark.createDataFrame([("a", 1.0, 8.0), ("a", 4.0, 4.0)], "series string, resources double, seconds double")
    assert {r["resources"]: (r["speedup"], r["efficiency"]) for r in scaling_table(runs).collect()} == {1.0: (1.0, 1.0), 4.0: (2.0, 0.5)}
    assert [r["ratio"] for r in weak_table(runs).orderBy("resources").collect()] == [1.0, 0.5]


def test_entry_module_lists_queries_with_matching_names():
    import __spark_entry__ as entry

    q, o = entry.queries(), entry.oracle_sql()
    assert set(o) <= set(q) and len(q) >= 80
    assert F is not None


def test_small_measures_and_node_memory(spark):
    from kernelblocks.measures import objective_gap, recall_by_class, rmse
    from kernelblocks.plans.blockplan import memory_model, memory_model_node

    scored = spark.createDataFrame([(1.0, 1.0), (1.0, 2.0), (2.0, 2.0), (2.0, 2.0)], "label double, pred double")
    assert abs(rmse(scored) - 0.5) < 1e-12 and objective_gap(3.0, 2.5) == 0.5
    assert {r["label"]: (r["recall"], r["n"]) for r in recall_by_class(scored).collect()} == {1.0: (0.5, 2), 2.0: (1.0, 2)}
    for threads in (1, 6):
        node = memory_model_node(10_000, 10, 50, 4000, 20, 4, threads)
        assert abs(node["total"] - memory_model(10_000, 10, 50, 4000, 20, 4, 4, threads)["total"]) < 1e-6


@pytest.mark.parametrize("name, source", [("block_bounds", "embedding:array<float>"), ("portable_normals", "c_custkey")])
def test_made_rows_come_from_a_table(spark, sf, name, source):
    got = QUERIES[name](spark, sf)
    plan = got._jdf.queryExecution().executedPlan().toString()
    assert any("ReadSchema" in line and source in line for line in plan.splitlines())
