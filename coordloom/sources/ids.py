"""Dense numbers 0..n-1 by order, without a one-partition window: range partitions, counts, offsets."""

from __future__ import annotations

from pyspark.sql import DataFrame, Window
from pyspark.sql import functions as F


def densify(df: DataFrame, order: list[str], name: str = "eid") -> DataFrame:
    """Adds the rank (from 0) in the given order, ties broken arbitrarily. The sorted data is written once, so that counts and ranks agree."""
    from coordloom.storage import materialise

    spark = df.sparkSession
    parts = max(1, int(spark.conf.get("spark.sql.shuffle.partitions")))
    ranged = materialise(df.repartitionByRange(parts, *order).withColumn("_part", F.spark_partition_id()), "ranged")
    counts = ranged.groupBy("_part").agg(F.count("*").alias("c"))  # one row per partition
    offsets = counts.select("_part", F.coalesce(F.sum("c").over(Window.orderBy("_part").rowsBetween(Window.unboundedPreceding, -1)), F.lit(0)).alias("_before"))
    rank = F.row_number().over(Window.partitionBy("_part").orderBy(*order)) - 1
    return ranged.withColumn("_rank", rank).join(F.broadcast(offsets), "_part").withColumn(name, (F.col("_before") + F.col("_rank")).cast("long")).drop("_part", "_before", "_rank")
