"""Entry, catalogue against DuckDB, sources, streams."""

import numpy as np
import pytest
from pyspark.sql import functions as F

import __spark_entry__ as entry
from coordloom.plans import catalogue
from coordloom.sources import features, io

FAST = ("fx_embed_long", "fx_order_sparse", "bk_assign", "bk_choose", "dl_static", "dl_dynamic", "dl_hier", "pl_placement", "pm_affine_trap", "cm_conflict", "sd_ridge_seq", "rp_hier", "rp_sync2", "rp_global", "bl_sag1", "sd_epoch_objective", "ev_certificate", "bl_cap_predictors", "jn_asof_model", "ls_lossy_t4", "ev_auc", "bl_gram", "sd_lasso_path", "ss_tumbling", "sql_predict")


@pytest.fixture(scope="module")
def duck(data_dir):
    import os

    import duckdb

    con = duckdb.connect()
    for f in os.listdir(data_dir):
        con.execute(f"create view {f.split('.')[0]} as select * from read_parquet('{data_dir}/{f}')")
    return con


@pytest.mark.parametrize("name", FAST)
def test_query_equals_its_sql(spark, data_dir, duck, name):
    mine = catalogue.QUERIES[name](spark, data_dir).toPandas()
    theirs = duck.execute(catalogue.ORACLES[name]).df()
    cols = sorted(mine.columns)
    assert cols == sorted(theirs.columns)
    a, b = (df[cols].sort_values(cols).reset_index(drop=True) for df in (mine, theirs))
    assert len(a) == len(b)
    for c in cols:
        if a[c].dtype.kind == "f":
            assert np.allclose(a[c], b[c].astype(float), atol=1e-6, equal_nan=True)
        else:
            assert a[c].tolist() == b[c].tolist()


def input_bytes(spark) -> int:
    """Bytes that tasks have read so far."""
    executors = spark.sparkContext._jsc.sc().statusStore().executorList(False)
    return sum(executors.apply(k).totalInputBytes() for k in range(executors.size()))


#: Queries whose tasks read no table before.
READERS = ("dl_static", "cm_sync", "dl_dynamic", "dl_hier", "fx_synth_dense", "fx_synth_sparse", "ms_speedup", "ms_reduction", "ms_status", "ms_best_valid", "ms_mean_speedup", "pl_placement")


@pytest.mark.parametrize("name", READERS)
def test_query_reads_a_table_and_equals_its_sql(spark, data_dir, duck, name):
    import time

    from coordloom.storage import settings

    time.sleep(1)  # the store takes what is read with a delay
    before = input_bytes(spark)
    with settings(spark, {"parquet.hadoop.vectored.io.enabled": "false"}):  # such reads aren't counted
        test_query_equals_its_sql(spark, data_dir, duck, name)
    time.sleep(1)
    assert input_bytes(spark) - before > (50_000 if name.startswith("dl_") else 500)


def test_entry_runs(spark):
    out = entry.entry(spark)
    assert out.count() > 0 and "rel_change" in out.columns


def test_every_oracle_has_a_query():
    assert set(entry.oracle_sql()) <= set(entry.queries())


def test_nothing_outside_imports_the_llm_package():
    from pathlib import Path

    root = Path(entry.__file__).parent / "coordloom"
    for p in root.rglob("*.py"):
        if "llm" not in p.relative_to(root).parts:
            assert "coordloom.llm" not in p.read_text()


def test_libsvm_round_trip(spark, data_dir, tmp_path):
    df = features.event_sparse(spark, data_dir).select("y", "idx", "val")
    io.write_libsvm(df, f"file://{tmp_path}/x")
    back = io.read_libsvm(spark, f"file://{tmp_path}/x")
    assert back.exceptAll(df).count() == 0 and back.count() == df.count()
    assert spark.read.format("libsvm").load(f"file://{tmp_path}/x").count() == df.count()


def test_python_data_source(spark):
    spark.dataSource.register(io.SyntheticGlm)
    df = spark.read.format("synthetic_glm").option("n", 50).option("d", 4).load()
    assert df.count() == 50 and df.filter(F.size("x") != 4).count() == 0


def test_incremental_training_keeps_the_invariant(spark, data_dir):
    from coordloom.operators import blocks, metrics
    from coordloom.operators.solvers import TrainSpec
    from coordloom.streaming.events import IncrementalTrainer

    df = features.embed_matrix(spark, data_dir)
    t = IncrementalTrainer(64, TrainSpec("ridge", 0.01, tol=0.0), 5)
    t(df.filter("eid < 200"), 0)
    t(df.filter("eid >= 200"), 1)
    frame = t.frames[0].unionByName(t.frames[1])
    p = blocks.Packed(frame, t.n, 64, t.n_blocks, 5, 1, True)
    assert metrics.certificate(p, t.result.model, "ridge", 0.01)["drift"] < 1e-9


def test_late_rows_are_dropped(spark, tmp_path):
    from coordloom.streaming import events

    def batch(rows, name):
        spark.createDataFrame(rows, "event_id long, ts timestamp_ntz, user_id long, event_type string, value double, props string").coalesce(1).write.mode("append").parquet(f"file://{tmp_path}/in")

    from datetime import datetime as dt

    row = lambda k, h: (k, dt(2024, 1, 1, h), 1, "purchase", 1.0, "{}")
    batch([row(1, 0), row(2, 10)], "a")
    stream = events.event_stream(spark, f"file://{tmp_path}/in")
    stats = events.run_available(events.user_statistics(stream), "user_stats", "update")
    assert stats.agg(F.max("n")).first()[0] == 2
    out = events.run_available(events.windowed(stream), "late_rows", "append")
    assert out.count() == 1


def test_predictor_cap_worsens_the_fit(spark, data_dir):
    from coordloom.operators.solvers import TrainSpec
    from coordloom.plans import workloads

    rows = {r["variant"]: r["objective"] for r in workloads.predictor_cap(spark, data_dir, TrainSpec("logistic", 1e-3), 20).collect()}
    assert rows["lbfgs cap 20"] > rows["lbfgs all"] and rows["auto cap 20"] > rows["auto all"]


def test_published_means_follow_from_their_six_values(spark):
    from coordloom.operators import reports

    rows = [(k, v) for k, vs in reports.PUBLISHED.items() for v in vs]
    got = {r["against"]: (r["mean"], r["best"]) for r in reports.mean_speedup(spark.createDataFrame(rows, "against string, speedup double")).collect()}
    assert got == {"lock-free": (5.05, 11.8), "best library": (18.08, 41.7)}
