"""SQL functions: scalars as SQL UDFs (inlined by the optimiser), table functions, Arrow functions for Python users."""



import pandas as pd
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F
from pyspark.sql.functions import pandas_udf, udtf

from coordloom.operators.permute import feistel
from coordloom.operators.topology import MACHINES, plan_placement

SCALARS = {
    "sigmoid": ("z DOUBLE", "DOUBLE", "1 / (1 + exp(-z))"),
    "soft_threshold": ("r DOUBLE, t DOUBLE", "DOUBLE", "signum(r) * greatest(abs(r) - t, 0D)"),
    "step_ridge": ("z DOUBLE, q DOUBLE, y DOUBLE, a DOUBLE, lamn DOUBLE", "DOUBLE", "(y - z - a) / (1 + q / lamn)"),
    "log_loss": ("m DOUBLE", "DOUBLE", "greatest(-m, 0D) + log1p(exp(-abs(m)))"),
    "glm_margin": ("x ARRAY<DOUBLE>, w ARRAY<DOUBLE>", "DOUBLE", "aggregate(zip_with(x, w, (a, b) -> a * b), 0D, (s, v) -> s + v)"),
}


def register(spark: SparkSession) -> None:
    for name, (args, returns, body) in SCALARS.items():
        spark.sql(f"CREATE OR REPLACE TEMPORARY FUNCTION {name}({args}) RETURNS {returns} RETURN {body}")
    spark.udtf.register("plan_placement_tvf", PlanPlacement)
    spark.udtf.register("deal_buckets_tvf", DealBuckets)


@udtf(returnType="node int, threads int")
class PlanPlacement:
    """plan_placement_tvf(machine, threads, data_node)."""

    def eval(self, machine: str, threads: int, data_node: int):
        yield from plan_placement(threads, MACHINES[machine], data_node)


@udtf(returnType="bid long, wid int, pos long")
class DealBuckets:
    """deal_buckets_tvf(nb, workers, epoch, seed): Feistel dealing of one group."""

    def eval(self, nb: int, workers: int, epoch: int, seed: int):
        import numpy as np

        for lo in range(0, nb, 65536):
            bids = np.arange(lo, min(nb, lo + 65536))
            for bid, rank in zip(bids.tolist(), feistel(bids, nb, epoch, seed).tolist(), strict=True):
                wid = rank * workers // nb
                yield bid, wid, rank - -(-wid * nb // workers)


@pandas_udf("double")
def logloss_agg(y: pd.Series, margin: pd.Series) -> float:  # a grouped aggregate
    import numpy as np

    m = y * margin
    return float((np.maximum(-m, 0) + np.log1p(np.exp(-np.abs(m)))).mean())


def sql_predict(df: DataFrame, w: list[float]) -> DataFrame:
    """margin and probability by the registered SQL functions."""
    spark = df.sparkSession
    register(spark)
    df.createOrReplaceTempView("_glm_examples")
    weights = ", ".join(f"{float(v)!r}D" for v in w)
    return spark.sql(f"SELECT eid, y, glm_margin(x, array({weights})) AS margin, sigmoid(glm_margin(x, array({weights}))) AS prob FROM _glm_examples")


def logloss_by_group(df: DataFrame, *keys: str) -> DataFrame:
    m = F.col("y") * F.col("margin")
    return df.groupBy(*keys).agg(F.avg(F.greatest(-m, F.lit(0.0)) + F.log1p(F.exp(-F.abs(m)))).alias("logloss"))
