"""Fixtures: the given tables encoded as labelled examples, with a splittable hash for the test rows."""

from __future__ import annotations

import json
from collections.abc import Iterator
from dataclasses import asdict, dataclass

import numpy as np
from pyspark.sql import Column, DataFrame, SparkSession, Window
from pyspark.sql import functions as F

STATUSES, PRIORITIES = ("F", "O", "P"), ("1-URGENT", "2-HIGH", "3-MEDIUM", "4-LOW", "5-NONE")
TEXT_DIM = 2048


@dataclass(frozen=True)
class FeatureSpec:
    name: str
    d: int
    layout: str  # dense or sparse

    def to_json(self) -> str:
        return json.dumps(asdict(self))


def read(spark: SparkSession, sf_dir: str, name: str) -> DataFrame:
    return spark.read.parquet(f"{sf_dir}/{name}.parquet")


def teacher(j: Column) -> Column:
    """The planted weight of column j."""
    return ((37 * j + 11) % 19 - 9) / 9.0


def md5_number(text: Column) -> Column:
    return F.conv(F.substring(F.md5(text), 1, 15), 16, 10).cast("long")


def line_matrix(spark: SparkSession, sf_dir: str) -> DataFrame:
    """(eid, y, y_flag, x) from lineitem; eid by rank over all columns (full rows are unique). y is planted, y_flag noise."""
    li = read(spark, sf_dir, "lineitem")
    order = ["l_orderkey", "l_linenumber", "l_partkey", "l_suppkey", "l_quantity", "l_extendedprice", "l_discount", "l_tax", "l_returnflag", "l_linestatus", "l_shipdate"]
    x = F.array(*[c.cast("double") for c in (F.col("l_quantity") / 50, F.col("l_extendedprice") / 105000, F.col("l_discount") * 10, F.col("l_tax") * 12.5, F.col("l_linenumber") / 7, F.lit(1.0))])
    from coordloom.sources.ids import densify

    rows = densify(li.select(*order, x.alias("x")), order, "eid")
    score = F.aggregate(F.zip_with("x", F.array(*[F.lit(((37 * j + 11) % 19 - 9) / 9.0) for j in range(6)]), lambda a, b: a * b), F.lit(0.0), lambda acc, v: acc + v)
    planted = F.when((score >= F.lit(LINE_CUT)) != (F.col("eid") % 20 == 0), 1.0).otherwise(-1.0)
    return rows.select("eid", planted.alias("y"), F.when(F.col("l_returnflag") == "R", 1.0).otherwise(-1.0).alias("y_flag"), "x")


#: A fixed value near the median of the planted score.
LINE_CUT = 0.9


def embed_matrix(spark: SparkSession, sf_dir: str) -> DataFrame:
    """(eid, y, x), y = +1 for labels under 5."""
    e = read(spark, sf_dir, "embeddings")
    return e.select(F.col("vec_id").alias("eid"), F.when(F.col("label") < 5, 1.0).otherwise(-1.0).alias("y"), F.col("embedding").cast("array<double>").alias("x"))


def order_sparse(spark: SparkSession, sf_dir: str) -> DataFrame:
    """(eid, y, idx, val): 8 of 66 columns set; orders joined with the dimensions."""
    o, c, n = read(spark, sf_dir, "orders"), read(spark, sf_dir, "customer"), read(spark, sf_dir, "nation")
    from coordloom.sources.bounded import small

    joined = o.join(c, o["o_custkey"] == c["c_custkey"]).join(small(n), c["c_nationkey"] == n["n_nationkey"])
    segment = F.pmod(md5_number(F.col("c_mktsegment")), F.lit(5))
    idx = F.array(
        F.array_position(F.array(*map(F.lit, STATUSES)), F.col("o_orderstatus")) - 1, 3 + F.substring("o_orderpriority", 1, 1).cast("int") - 1, 7 + F.month("o_orderdate"), 20 + segment, 25 + F.col("n_nationkey"), 50 + F.col("n_regionkey"),
        55 + F.least(F.lit(9), F.floor(F.col("o_totalprice") / 50000)), F.lit(65),
    )
    idx = F.transform(idx, lambda i: i.cast("int"))
    score = F.aggregate(F.transform(idx, lambda j: ((37 * j + 11) % 19 - 9) / F.lit(9.0)), F.lit(0.0), lambda acc, v: acc + v)
    planted = F.when((score >= 0) != (F.col("o_orderkey") % 20 == 0), 1.0).otherwise(-1.0)
    return joined.select(F.col("o_orderkey").alias("eid"), planted.alias("y"), idx.alias("idx"), F.array_repeat(F.lit(1.0), 8).alias("val"))


def text_hash(spark: SparkSession, sf_dir: str) -> DataFrame:
    """(eid, y, y_toxic, idx, val): hashed lower-case tokens of the labelled documents, ln(1 + count), normalised."""
    d, l = read(spark, sf_dir, "documents"), read(spark, sf_dir, "labels")
    from coordloom.sources.ids import densify

    labelled = densify(d.join(l, "doc_id").select("doc_id", "text", "quality", "toxic"), ["doc_id"], "eid")
    tokens = labelled.select("eid", F.explode(F.split(F.lower("text"), r"[^a-z0-9]+")).alias("t")).filter("t <> ''")
    slots = tokens.groupBy("eid", F.pmod(md5_number(F.col("t")), F.lit(TEXT_DIM)).cast("int").alias("i")).agg(F.log1p(F.count("*").cast("double")).alias("v"))
    rows = slots.groupBy("eid").agg(F.sort_array(F.collect_list(F.struct("i", "v"))).alias("r"), F.sqrt(F.sum(F.col("v") * F.col("v"))).alias("norm"))
    full = labelled.select("eid", "quality", "toxic").join(rows, "eid", "left")
    none_i, none_v = F.array().cast("array<int>"), F.array().cast("array<double>")
    return full.select(
        "eid", F.when(F.col("quality") == 1, 1.0).otherwise(-1.0).alias("y"), F.when(F.col("toxic") == 1, 1.0).otherwise(-1.0).alias("y_toxic"),
        F.coalesce(F.col("r.i"), none_i).alias("idx"), F.coalesce(F.transform("r", lambda e: e["v"] / F.col("norm")), none_v).alias("val"),
    )


def event_sparse(spark: SparkSession, sf_dir: str) -> DataFrame:
    """hour, weekday, user bucket, props.k decile, value, constant; y = purchase. d = 107."""
    e = read(spark, sf_dir, "events")
    k = F.get_json_object("props", "$.k").cast("int")
    idx = F.array(F.hour("ts"), 23 + F.dayofweek("ts"), 31 + F.pmod("user_id", F.lit(64)), 95 + F.least(F.lit(9), F.floor(k / 10)), F.lit(105), F.lit(106))
    return e.select(F.col("event_id").alias("eid"), F.when(F.col("event_type") == "purchase", 1.0).otherwise(-1.0).alias("y"), F.transform(idx, lambda i: i.cast("int")).alias("idx"), F.concat(F.array_repeat(F.lit(1.0), 4), F.array((F.col("value") / 100).cast("double"), F.lit(1.0))).alias("val"))


def _hash_int(i: Column, j: Column | int, salt: int) -> Column:
    """A small integer mix that Spark and DuckDB agree on (all products under 2^63)."""
    a = (i * 7919 + j * 104729 + salt * 15485863) % 2147483647
    b = (a * 48271) % 2147483647
    return ((b + (b % 65536) * 40503) * 16807) % 2147483647


def _hash_numbers(i: np.ndarray, j: int, salt: int) -> np.ndarray:
    """``_hash_int`` of many i; fmod, as SQL's % keeps the sign."""
    a = np.fmod(i * 7919 + (j * 104729 + salt * 15485863), 2147483647)
    b = np.fmod(a * 48271, 2147483647)
    return np.fmod((b + np.fmod(b, 65536) * 40503) * 16807, 2147483647)


def synth_dense(spark: SparkSession, n: int, d: int = 100) -> DataFrame:
    """F6a over the numbers 0 to n - 1."""
    return synth_dense_of(spark.range(n), d)


def synth_dense_of(ids: DataFrame, d: int = 100) -> DataFrame:
    """Values in [-1, 1] from an integer hash of the examples' ``id``; the sign of the teacher, 5 % flipped."""
    def run(batches: Iterator) -> Iterator:
        for batch in batches:
            i, x = np.asarray(batch.column(0)), np.empty((batch.num_rows, d))
            score = np.zeros(len(i))
            for j in range(d):
                x[:, j] = np.fmod(_hash_numbers(i, j, 1), 2001) - 1000
            x /= 1000.0
            for j in range(d):  # added up column by column, as SQL does
                score += x[:, j] * ((37 * j + 11) % 19 - 9) / 9.0
            y = np.where((score >= 0) != (np.fmod(i, 20) == 0), 1.0, -1.0)
            cuts = np.arange(0, d * len(i) + 1, d, dtype=np.int32) if d else np.zeros(len(i) + 1, np.int32)
            yield pa.RecordBatch.from_arrays([pa.array(i), pa.array(y), pa.ListArray.from_arrays(pa.array(cuts), pa.array(x.ravel()))], names=["eid", "y", "x"])

    import pyarrow as pa

    return ids.select(F.col("id").cast("long")).mapInArrow(run, "eid long, y double, x array<double>")


def synth_sparse(spark: SparkSession, n: int, d: int = 1000, draws: int = 10) -> DataFrame:
    """F6b over the numbers 0 to n - 1."""
    return synth_sparse_of(spark.range(n), d, draws)


def synth_sparse_of(ids: DataFrame, d: int = 1000, draws: int = 10) -> DataFrame:
    """``draws`` uniform columns a row (1 %), doubles removed, value 1."""
    idx = F.array_sort(F.array_distinct(F.transform(F.sequence(F.lit(0), F.lit(draws - 1)), lambda j: (_hash_int(F.col("id"), j, 2) % d).cast("int"))))
    rows = ids.select(F.col("id").alias("eid"), idx.alias("idx"))
    score = F.aggregate(F.transform("idx", lambda j: ((37 * j + 11) % 19 - 9) / F.lit(9.0)), F.lit(0.0), lambda acc, v: acc + v)
    return rows.select("eid", F.when((score >= 0) != (F.col("eid") % 20 == 0), 1.0).otherwise(-1.0).alias("y"), "idx", F.transform("idx", lambda _: F.lit(1.0)).alias("val"))


WIDE_DIM = 1109


def wide_line(spark: SparkSession, sf_dir: str) -> DataFrame:
    """F8: (eid, y, idx, val): 9 of 1109 columns; lineitem joined with part, supplier and orders."""
    li, p, s, o = (read(spark, sf_dir, t) for t in ("lineitem", "part", "supplier", "orders"))
    from coordloom.sources.ids import densify

    order = ["l_orderkey", "l_linenumber", "l_partkey", "l_suppkey", "l_quantity", "l_extendedprice", "l_discount", "l_tax", "l_returnflag", "l_linestatus", "l_shipdate"]
    rows = densify(li.select(*order), order, "eid")
    j = rows.join(p, rows["l_partkey"] == p["p_partkey"]).join(s, rows["l_suppkey"] == s["s_suppkey"]).join(o, rows["l_orderkey"] == o["o_orderkey"])
    flag = F.array_position(F.array(*map(F.lit, "ANR")), F.col("l_returnflag")) - 1
    status = 3 + F.when(F.col("l_linestatus") == "O", 1).otherwise(0)
    idx = F.array(
        flag, status, 4 + F.col("l_linenumber"), 12 + F.pmod(md5_number(F.col("p_brand")), F.lit(25)), 37 + F.pmod(md5_number(F.col("p_type")), F.lit(6)), 43 + F.col("s_nationkey"),
        68 + F.substring("o_orderpriority", 1, 1).cast("int") - 1, 72 + F.month("l_shipdate"), 85 + F.pmod("l_partkey", F.lit(1024)),
    )
    idx = F.transform(idx, lambda i: i.cast("int"))
    score = F.aggregate(F.transform(idx, lambda k: ((37 * k + 11) % 19 - 9) / F.lit(9.0)), F.lit(0.0), lambda acc, v: acc + v)
    return j.select("eid", F.when((score >= 0) != (F.col("eid") % 20 == 0), 1.0).otherwise(-1.0).alias("y"), idx.alias("idx"), F.array_repeat(F.lit(1.0), 9).alias("val"))
