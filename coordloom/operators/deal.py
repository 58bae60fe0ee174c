"""Dealing of rows to workers for an epoch: static, dynamic inside groups, or global.

The solver's tasks count ranks themselves (kernels.Dealer). ``assign`` says the same as columns, for reports and checks;
its windows hold block numbers of one group, no data.
"""

from __future__ import annotations

from pyspark.sql import Column, DataFrame, SparkSession, Window
from pyspark.sql import functions as F

from coordloom.operators.permute import key


def _div(a: Column, b: Column | int) -> Column:
    return F.floor(a / b).cast("long")


def _bounds(n_blocks: int, groups: int) -> tuple[Column, Column]:
    """(first block, number of blocks) of a row's group."""
    first, after = (F.ceil((F.col("gid") + k) * n_blocks / groups).cast("long") for k in (0, 1))
    return first, after - first


def own_worker(n_blocks: int, groups: int, per_group: int) -> Column:
    """The worker that a block belongs to under static dealing: runs of neighbours."""
    first, size = _bounds(n_blocks, groups)
    return (F.col("gid") * per_group + _div((F.col("bid") - first) * per_group, size)).cast("int")


def global_ranks(spark: SparkSession, n_blocks: int, epoch: int, seed: int, order: str = "md5") -> DataFrame:
    """(bid, rank) over all blocks; keys that aren't ranks themselves are ranked by range partitions and offsets."""
    from coordloom.sources.ids import densify

    keyed = spark.range(n_blocks).select(F.col("id").alias("bid"), key(F.col("id"), epoch, seed, order, n_blocks).alias("_key"))
    if order != "md5":
        return keyed.withColumnRenamed("_key", "rank")
    return densify(keyed, ["_key", "bid"], "rank").drop("_key")


def assign(frame: DataFrame, n_blocks: int, groups: int, per_group: int, deal: str, epoch: int, seed: int, order: str = "md5") -> DataFrame:
    """Adds wid (0..groups*per_group-1) and pos, the place in the worker's list.

    rank r of nb rows in a group goes to worker floor(r k / nb), a run of consecutive ranks. Static: r is the
    row's number, the order inside the worker is drawn anew; dynamic: r is the rank by the epoch's key.
    """
    first, size = _bounds(n_blocks, groups)
    keyed = frame.withColumns({"_first": first, "_nb": size, "_key": key(F.col("bid"), epoch, seed, order, n_blocks)})
    if deal == "static":
        drawn = keyed.withColumn("wid", own_worker(n_blocks, groups, per_group))
        out = drawn.withColumn("pos", F.row_number().over(Window.partitionBy("wid").orderBy("_key", "bid")).cast("long") - 1)
    elif deal == "dynamic":
        ranked = keyed.withColumn("_rank", F.row_number().over(Window.partitionBy("gid").orderBy("_key", "bid")).cast("long") - 1)
        slot = _div(F.col("_rank") * per_group, F.col("_nb"))
        out = ranked.withColumns({"wid": (F.col("gid") * per_group + slot).cast("int"), "pos": F.col("_rank") - F.ceil(slot * F.col("_nb") / per_group).cast("long")})
    elif deal == "global":
        workers = per_group * groups
        slot = _div(F.col("rank") * workers, n_blocks)
        ranked = keyed.join(global_ranks(frame.sparkSession, n_blocks, epoch, seed, order), "bid")
        out = ranked.withColumns({"wid": slot.cast("int"), "pos": F.col("rank") - F.ceil(slot * n_blocks / workers).cast("long")}).drop("rank")
    else:
        raise ValueError(f"unknown dealing {deal!r}")
    return out.drop("_first", "_nb", "_key", "_rank")


def busy_workers(n_blocks: int, groups: int, per_group: int, deal: str = "dynamic") -> int:
    """Workers that get a row."""
    if deal == "global":
        return min(groups * per_group, n_blocks)
    sizes = [-(-(g + 1) * n_blocks // groups) - -(-g * n_blocks // groups) for g in range(groups)]
    return sum(min(per_group, s) for s in sizes)
