"""Predictions, losses, certificates and counted costs."""

from __future__ import annotations

from collections.abc import Iterator

import numpy as np
from pyspark.sql import Column, DataFrame, Window
from pyspark.sql import functions as F

from coordloom.operators import kernels, losses
from coordloom.operators.blocks import Packed, with_slots
from coordloom.operators.solvers import Model
from coordloom.storage import CO_LOCATED, materialise, settings

#: A hash split: rows with md5 prefix mod 5 = 0 are held out.


def is_test(eid: Column) -> Column:
    return F.conv(F.substring(F.md5(eid.cast("string")), 1, 15), 16, 10).cast("long") % 5 == 0


def margin_dense(x: Column, w) -> Column:
    weights = F.array(*[F.lit(float(v)) for v in w])
    return F.aggregate(F.zip_with(x, weights, lambda a, b: a.cast("double") * b), F.lit(0.0), lambda acc, v: acc + v)


def predict(df: DataFrame, model: Model, kind: str = "margin") -> DataFrame:
    """Adds ``margin``, and ``prob`` or ``class``. Arrow batches against a broadcast w, so that d isn't bound by the plan's size."""
    shared, dense = df.sparkSession.sparkContext.broadcast(model.w), "x" in df.columns
    keep = [f for f in df.schema.fields]

    def run(batches: Iterator) -> Iterator:
        import pyarrow as pa

        w = shared.value
        for batch in batches:
            if dense:
                col = batch.column("x")
                bounds, val, idx = np.asarray(col.offsets), np.asarray(col.flatten(), dtype=float), None
            else:
                col = batch.column("val")
                bounds, val, idx = np.asarray(col.offsets), np.asarray(col.flatten(), dtype=float), np.asarray(batch.column("idx").flatten())
            bounds = bounds - bounds[0]
            sizes = np.diff(bounds)
            idx = np.arange(len(val)) - np.repeat(bounds[:-1], sizes) if idx is None else idx
            row = np.repeat(np.arange(batch.num_rows), sizes)
            margins = np.bincount(row, weights=val * w[idx], minlength=batch.num_rows)
            yield pa.RecordBatch.from_arrays([*batch.columns, pa.array(margins)], names=[*batch.schema.names, "margin"])

    from pyspark.sql.types import DoubleType, StructField, StructType

    out = df.mapInArrow(run, StructType([*keep, StructField("margin", DoubleType())]))
    if kind == "prob":
        out = out.withColumn("prob", 1 / (1 + F.exp(-F.col("margin"))))
    if kind == "class":
        out = out.withColumn("class", F.when(F.col("margin") >= 0, 1.0).otherwise(-1.0))
    return out


def logloss(df: DataFrame) -> DataFrame:
    return df.agg(F.count("*").alias("n"), F.avg(losses.logloss_expr(F.col("y") * F.col("margin"))).alias("logloss"))


def accuracy(df: DataFrame) -> DataFrame:
    hit = F.when((F.col("margin") >= 0) == (F.col("y") > 0), 1.0).otherwise(0.0)
    return df.agg(F.avg(hit).alias("accuracy"))


def confusion(df: DataFrame) -> DataFrame:
    return df.groupBy((F.col("y") > 0).alias("actual"), (F.col("margin") >= 0).alias("predicted")).agg(F.count("*").alias("n"))


def auc(df: DataFrame) -> DataFrame:
    """Rank sum with average ranks of ties. Scores are counted, dealt to ranges and summed up inside each; ranges add the totals of those before."""
    spark = df.sparkSession
    tied = df.groupBy("margin").agg(F.count("*").alias("c"), F.count_if(F.col("y") > 0).alias("p"))
    parts = max(1, int(spark.conf.get("spark.sql.shuffle.partitions")))
    ranged = materialise(tied.repartitionByRange(parts, "margin").withColumn("_part", F.spark_partition_id()), "scores")
    sums = ranged.groupBy("_part").agg(F.sum("c").alias("_c"))  # one row per partition
    before = sums.select("_part", F.coalesce(F.sum("_c").over(Window.orderBy("_part").rowsBetween(Window.unboundedPreceding, -1)), F.lit(0)).alias("_before"))
    inside = Window.partitionBy("_part").orderBy("margin").rowsBetween(Window.unboundedPreceding, Window.currentRow)
    ranked = ranged.withColumn("_sum", F.sum("c").over(inside)).join(F.broadcast(before), "_part")
    rank = F.col("_before") + F.col("_sum") - (F.col("c") - 1) / 2
    total = ranked.agg(F.sum(rank * F.col("p")).alias("s"), F.sum("p").alias("p"), F.sum("c").alias("n"))
    return total.select(((F.col("s") - F.col("p") * (F.col("p") + 1) / 2) / (F.col("p") * (F.col("n") - F.col("p")))).alias("auc"))


def rel_change(pairs: DataFrame, now: str, before: str) -> DataFrame:
    """|now - before| / |now| over the numbers in two columns: the test of convergence."""
    return pairs.agg(F.sqrt(F.sum((F.col(now) - F.col(before)) ** 2) / F.sum(F.col(now) ** 2)).alias("rel_change"))


def evaluate(df: DataFrame, model: Model) -> dict[str, float]:
    scored = predict(df, model)
    hit = F.when((F.col("margin") >= 0) == (F.col("y") > 0), 1.0).otherwise(0.0)
    row = scored.agg(F.count("*").alias("n"), F.avg(losses.logloss_expr(F.col("y") * F.col("margin"))).alias("logloss"), F.avg(hit).alias("accuracy")).first()
    return row.asDict()


def certificate(packed: Packed, model: Model, loss: str, lam: float) -> dict[str, float]:
    """primal, dual, gap, and the largest |w - A alpha / (lam n)| (0 unless updates were lost)."""
    spark = packed.frame.sparkSession
    shared, n, d = spark.sparkContext.broadcast(model.w), packed.n, packed.d

    def run(batches: Iterator) -> Iterator:
        import pyarrow as pa

        w, primal, dual, v = shared.value, 0.0, 0.0, np.zeros(d)
        for batch in batches:
            row, idx, val, y = kernels.examples_of(batch)
            a = kernels.alphas_of(batch, len(y))
            primal += float(np.sum(losses.value(loss, np.bincount(row, weights=val * w[idx], minlength=len(y)), y)))
            dual -= float(np.sum(losses.conjugate(loss, y, a)))
            v += np.bincount(idx, weights=val * a[row], minlength=d)
        yield pa.RecordBatch.from_arrays([pa.array([primal]), pa.array([dual]), pa.array([v], pa.list_(pa.float64()))], names=["primal", "dual", "v"])

    with settings(spark, CO_LOCATED):
        frame = packed.frame if "slot" in packed.frame.columns else with_slots(packed.frame, packed.slots)
        frame = frame.join(model.alpha.hint("merge"), ["slot", "bid"], "left") if model.alpha is not None else frame.withColumn("alpha", F.lit(None).cast("array<double>"))
        rows = frame.select("y", "indptr", "idx", "val", "alpha").mapInArrow(run, "primal double, dual double, v array<double>").collect()  # one row per task
    v = sum((np.array(r["v"]) for r in rows), np.zeros(d)) / (lam * n)
    primal = sum(r["primal"] for r in rows) / n + lam / 2 * float(model.w @ model.w)
    dual = sum(r["dual"] for r in rows) / n - lam / 2 * float(v @ v)
    return {"primal": primal, "dual": dual, "gap": primal - dual, "drift": float(np.abs(v - model.w).max()) if d else 0.0}


# Counted costs


def alpha_traffic(n: int, line_bytes: int, bucketed: bool) -> int:
    """Bytes of cache lines moved for the model in an epoch."""
    return -(-8 * n // line_bytes) * line_bytes if bucketed else n * line_bytes


def permuted(n: int, bucket: int) -> int:
    return -(-n // bucket)


def sync_bytes(d: int, workers: int, groups: int = 1, syncs: int = 1) -> dict[str, int]:
    return {"flat": syncs * workers * 8 * d, "across": syncs * groups * 8 * d, "within": syncs * workers * 8 * d}


def conflict(p: Column, workers: Column | int) -> Column:
    """Chance that another of the workers touches a component of density p."""
    k = workers if isinstance(workers, Column) else F.lit(workers)
    return 1 - F.pow(1 - p, k - 1)


def collisions(p: Column, workers: Column | int) -> Column:
    k = workers if isinstance(workers, Column) else F.lit(workers)
    return k * p - (1 - F.pow(1 - p, k))
