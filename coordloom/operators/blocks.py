"""Rows of consecutive examples, the unit of dealing; buckets inside a row are the unit of its order."""

from __future__ import annotations

from collections.abc import Iterator
from dataclasses import dataclass, field, replace

import numpy as np
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from coordloom.operators.stream import EXAMPLES, Orders
from coordloom.storage import SMALL_BATCHES, Bucketed, settings

#: Examples of a slab at most, and values of one (where the number of columns says so).
SLAB, SLAB_CELLS = 1024, 1 << 14
#: A single group of so many stored values or fewer (half a gigabyte) stays in its task for the whole run: the same passes, without a job for each.
RESIDENT_CELLS = 64 << 20
#: Values of a bucket of ``pack_spread``, in bytes.
SPREAD_BYTES = 128 << 20


@dataclass
class Packed:
    """Block rows (slot, gid, bid, eids, y, indptr, idx, val) of ``n`` examples with ``d`` features; idx is null for dense ones.

    ``bucket`` is the number of examples of a row; ``unit`` that of the buckets which are permuted inside it (the whole row if 0).
    A stored frame is a bucketed table: one bucket, one file and one task per group. Rows of ``slab`` over 1 are slabs: so many rows
    of consecutive examples each, which the task of a resident run takes apart; ``n_blocks`` and ``bucket`` count what is dealt.
    """

    frame: DataFrame
    n: int
    d: int
    n_blocks: int
    bucket: int
    groups: int
    dense: bool
    slots: tuple[int, ...] = (0,)
    unit: int = 0
    table: Bucketed | None = None
    cells: int = 0  # stored values
    slab: int = 1
    orders: Orders = field(default_factory=Orders)  # what runs that don't stay in their task share

    def group_first(self, gid) -> int:
        """The first block of a group: gid = floor(bid * G / nb)."""
        return -(-gid * self.n_blocks // self.groups)

    def group_blocks(self, gid: int) -> int:
        return self.group_first(gid + 1) - self.group_first(gid)

    def plain(self) -> DataFrame:
        """The rows for passes in any order: split by size, so that they use all cores whatever the number of groups."""
        return self.table.plain() if self.table else self.frame

    def release(self) -> None:
        """Delete the stored blocks."""
        if self.table:
            self.table.drop()


def by_group(df: DataFrame, groups: int) -> DataFrame:
    """One partition per group, gid 0 to 0 and so on: hash partitioning would put two groups in one."""
    return df.repartitionById(groups, "gid")


def group_slots(spark: SparkSession, groups: int) -> tuple[int, ...]:
    """One integer per group, such that Spark's bucketing by it puts each group in a bucket of its own."""
    found: dict[int, int] = {}
    size = 8 * groups + 64
    lo = 0
    while len(found) < groups:
        for k, bucket in spark.range(lo, lo + size, 1, 1).select("id", F.pmod(F.hash(F.col("id").cast("int")), F.lit(groups))).collect():
            found.setdefault(bucket, k)
        lo, size = lo + size, 2 * size
    return tuple(found[b] for b in range(groups))


def with_slots(frame: DataFrame, slots: tuple[int, ...]) -> DataFrame:
    return frame.withColumn("slot", F.element_at(F.array(*map(F.lit, slots)), F.col("gid") + 1).cast("int"))


def pack(df: DataFrame, n: int, d: int, bucket: int = 1, groups: int = 1, store: bool = True, unit: int = 0) -> Packed:
    """``df``: (eid, y, x) or (eid, y, idx, val) with eid 0..n-1, which is checked. One shuffle; afterwards the data stays with its group."""
    dense = "x" in df.columns
    n_blocks = max(1, -(-n // bucket))
    groups = max(1, min(groups, n_blocks))
    bid = F.floor(F.col("eid") / bucket)
    row = F.struct("eid", "y", *([F.col("x").alias("val")] if dense else ["idx", "val"]))
    grouped = df.withColumn("bid", bid.cast("long")).groupBy("bid").agg(F.sort_array(F.collect_list(row)).alias("r"))
    first = F.col("bid") * bucket
    whole = F.col("r.eid") == F.sequence(first, F.least(first + bucket, F.lit(n)) - 1)
    in_range = (F.col("bid") >= 0) & (F.col("bid") < n_blocks)
    checked = F.when(in_range & F.coalesce(whole, F.lit(False)), F.col("r.eid")).otherwise(F.raise_error(F.format_string("the numbers of block %d are not the consecutive ones of 0..n-1", "bid")))
    sizes = F.transform("r", lambda e: F.size(e["val"]))
    if dense and d:
        indptr = F.sequence(F.lit(0), F.size("r") * d, F.lit(d))
    else:  # a running sum; linear in the bucket but for the copying of integers
        indptr = F.aggregate(sizes, F.array(F.lit(0)), lambda acc, s: F.concat(acc, F.array(F.element_at(acc, -1) + s)))
    frame = grouped.select(
        F.floor(F.col("bid") * groups / n_blocks).cast("int").alias("gid"), "bid",
        checked.alias("eids"), F.col("r.y").alias("y"), indptr.alias("indptr"),
        (F.lit(None).cast("array<int>") if dense else F.flatten("r.idx")).alias("idx"), F.flatten("r.val").cast("array<double>").alias("val"),
    )
    out = Packed(by_group(frame, groups), n, d, n_blocks, bucket, groups, dense, unit=unit)
    if not store:
        return out
    out = _stored(out, out.frame)
    stored, cells = out.plain().agg(F.count("*"), F.sum(F.size("val"))).first()
    if n and stored != n_blocks:
        raise ValueError("some of the numbers 0..n-1 have no example")
    return replace(out, cells=cells or 0)


def slabs_of(batches: Iterator, per: int, n: int) -> Iterator:
    """Slabs of ``per`` examples out of batches (eid, y, val) or (eid, y, idx, val) that come sorted by eid."""
    import pyarrow as pa

    def lists(cuts: np.ndarray, values: np.ndarray) -> pa.ListArray:
        return pa.ListArray.from_arrays(pa.array(cuts.astype(np.int32)), pa.array(values))

    def build(rows: pa.RecordBatch) -> pa.RecordBatch:
        eid, sizes = np.asarray(rows["eid"]), np.asarray(rows["val"].value_lengths())
        bid = eid // per
        at = np.concatenate(([0], np.flatnonzero(bid[1:] != bid[:-1]) + 1, [len(eid)]))
        first, m = bid[at[:-1]] * per, np.diff(at)
        ends = np.concatenate(([0], np.cumsum(sizes, dtype=np.int64)))
        if first[0] < 0 or (m != np.minimum(first + per, n) - first).any() or (eid != np.repeat(first - at[:-1], m) + np.arange(len(eid))).any():
            raise ValueError("the numbers of some examples are not the consecutive ones of 0..n-1")
        indptr = np.concatenate([ends[lo : hi + 1] - ends[lo] for lo, hi in zip(at[:-1].tolist(), at[1:].tolist(), strict=True)]).astype(np.int32)
        idx = lists(ends[at], np.asarray(rows["idx"].flatten())) if "idx" in rows.schema.names else pa.nulls(len(m), pa.list_(pa.int32()))
        columns = [pa.array(bid[at[:-1]]), lists(at, eid), lists(at, np.asarray(rows["y"])), lists(at + np.arange(len(at)), indptr), idx, lists(ends[at], np.asarray(rows["val"].flatten()))]
        return pa.RecordBatch.from_arrays(columns, names=["bid", "eids", "y", "indptr", "idx", "val"])

    held, count = [], 0
    whole = lambda: pa.Table.from_batches(held).combine_chunks().to_batches()[0]
    for batch in batches:
        if batch.num_rows:
            held.append(batch)
            count += batch.num_rows
        if count >= 4 * per:
            rows = whole()
            bid = np.asarray(rows["eid"]) // per
            cut = int(np.searchsorted(bid, bid[-1]))  # the last slab may not be whole yet
            if cut:
                yield build(rows.slice(0, cut))
            held, count = [rows.slice(cut)], count - cut
    if count:
        yield build(whole())


def pack_slabs(df: DataFrame, n: int, d: int, bucket: int = 1, most: int = RESIDENT_CELLS) -> Packed:
    """``pack`` for one group whose runs stay in their task: rows are stored many together and taken apart there. With more than ``most`` values it is ``pack``."""
    dense = "x" in df.columns
    slab = max(1, min(SLAB, SLAB_CELLS // d if dense and d else SLAB) // bucket)
    if dense and n * d + n > most or slab == 1 or not n:
        return pack(df, n, d, bucket)
    per = slab * bucket
    values = [F.col("x").cast("array<double>").alias("val")] if dense else [F.col("idx").cast("array<int>").alias("idx"), F.col("val").cast("array<double>").alias("val")]
    kinds = "bid long, eids array<long>, y array<double>, indptr array<int>, idx array<int>, val array<double>"
    spark = df.sparkSession
    with settings(spark, SMALL_BATCHES):
        rows = df.select(F.col("eid").cast("long").alias("eid"), F.col("y").cast("double").alias("y"), *values)
        together = rows.repartition(F.floor(F.col("eid") / per)).sortWithinPartitions("eid").mapInArrow(lambda batches: slabs_of(batches, per, n), kinds)
        frame = by_group(together.select(F.lit(0).alias("gid"), "*"), 1)
        out = _stored(Packed(frame, n, d, -(-n // bucket), bucket, 1, dense, slab=slab), frame)
    stored, cells = out.plain().agg(F.sum(F.size("y")), F.sum(F.size("val"))).first()
    if stored != n:
        raise ValueError("some of the numbers 0..n-1 have no example")
    if cells + n > most:
        out.release()
        return pack(df, n, d, bucket)
    return replace(out, cells=cells)


def pack_runs(df: DataFrame, n: int, d: int, bucket: int = 1) -> Packed:
    """For runs of one group: slabs in one bucket where the runs stay in their task, else spread over many, as the runs read orders of them."""
    dense = "x" in df.columns
    cells = n * d if dense else df.agg(F.sum(F.size("val"))).first()[0] or 0
    return pack_slabs(df, n, d, bucket) if cells + n <= RESIDENT_CELLS or n > EXAMPLES else pack_spread(df, n, d, bucket, cells)


def pack_spread(df: DataFrame, n: int, d: int, bucket: int, cells: int) -> Packed:
    """Slabs of one group by ranges in many buckets, so that no task takes them all; one exchange."""
    dense, spark = "x" in df.columns, df.sparkSession
    slab = max(1, min(SLAB, SLAB_CELLS // d if dense and d else SLAB) // bucket)
    per = slab * bucket
    stored = -(-n // per)
    spread = max(1, min(stored, max(spark.sparkContext.defaultParallelism, -(-8 * cells // SPREAD_BYTES))))
    slots, share = group_slots(spark, spread), lambda number: F.least(F.lit(spread - 1), F.floor(number * spread / stored)).cast("int")
    values = [F.col("x").cast("array<double>").alias("val")] if dense else [F.col("idx").cast("array<int>").alias("idx"), F.col("val").cast("array<double>").alias("val")]
    kinds = "bid long, eids array<long>, y array<double>, indptr array<int>, idx array<int>, val array<double>"
    with settings(spark, SMALL_BATCHES):
        rows = df.select(F.col("eid").cast("long").alias("eid"), F.col("y").cast("double").alias("y"), *values)
        dealt = rows.withColumn("place", share(F.floor(F.col("eid") / per))).repartitionById(spread, "place").drop("place")
        frame = dealt.sortWithinPartitions("eid").mapInArrow(lambda batches: slabs_of(batches, per, n), kinds)
        slot = F.element_at(F.array(*map(F.lit, slots)), share(F.col("bid")) + 1).cast("int")
        table = Bucketed(frame.select(F.lit(0).alias("gid"), "*", slot.alias("slot")), "blocks", spread)
    found, values = table.plain().agg(F.sum(F.size("y")), F.sum(F.size("val"))).first()
    if found != n:
        raise ValueError("some of the numbers 0..n-1 have no example")
    return Packed(table.frame(), n, d, -(-n // bucket), bucket, 1, dense, slots, table=table, cells=values, slab=slab)


def rebucket(packed: Packed, bucket: int) -> Packed:
    """The same slabs, dealt in rows of another size that divides a slab."""
    per = packed.slab * packed.bucket
    if packed.slab == 1 or per % bucket:
        raise ValueError("not slabs of whole rows of that size")
    return replace(packed, bucket=bucket, slab=per // bucket, n_blocks=-(-packed.n // bucket))


def _stored(packed: Packed, grouped: DataFrame) -> Packed:
    slots = group_slots(grouped.sparkSession, packed.groups)
    table = Bucketed(with_slots(grouped, slots), "blocks", packed.groups)
    return replace(packed, frame=table.frame(), slots=slots, table=table)


def regroup(packed: Packed, groups: int) -> Packed:
    """The same blocks stored once more for other groups."""
    groups = max(1, min(groups, packed.n_blocks))
    if groups == packed.groups and packed.table:
        return packed
    if packed.slab > 1:
        raise ValueError("slabs belong to one group; use pack")
    frame = packed.plain().drop("slot").withColumn("gid", F.floor(F.col("bid") * groups / packed.n_blocks).cast("int"))
    return _stored(replace(packed, groups=groups), by_group(frame, groups))


def unpack(packed: Packed) -> DataFrame:
    """(eid, y, idx, val) per example; dense examples get idx 0..d-1."""
    one = packed.plain().select("*", F.posexplode("eids").alias("k", "eid"))
    start, size = F.col("indptr")[F.col("k")], F.col("indptr")[F.col("k") + 1] - F.col("indptr")[F.col("k")]
    idx = F.when(F.col("idx").isNull(), F.sequence(F.lit(0), size - 1)).otherwise(F.slice("idx", start + 1, size))
    return one.select("eid", F.col("y")[F.col("k")].alias("y"), idx.alias("idx"), F.slice("val", start + 1, size).alias("val"))
