"""Sources and sinks: libsvm text, a Python data source of synthetic examples, partitioned and bucketed tables, common file formats."""

from __future__ import annotations

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F
from pyspark.sql.datasource import DataSource, DataSourceReader, InputPartition


def load(spark: SparkSession, path: str, fmt: str = "parquet", schema: str | None = None, **options) -> DataFrame:
    """Any Spark format; text formats need a schema, so that nothing is guessed from the data."""
    if fmt in ("csv", "json") and schema is None:
        raise ValueError(f"{fmt} needs a schema")
    reader = spark.read.format(fmt).options(**options)
    return (reader.schema(schema) if schema else reader).load(path)


def write_libsvm(examples: DataFrame, path: str) -> None:
    """(y, idx, val) as label index:value lines, indices from 1."""
    pairs = F.array_join(F.zip_with("idx", "val", lambda i, v: F.concat_ws(":", (i + 1).cast("string"), v.cast("string"))), " ")
    examples.select(F.concat_ws(" ", F.col("y").cast("string"), pairs).alias("value")).write.text(path)


def read_libsvm(spark: SparkSession, path: str) -> DataFrame:
    """(y, idx, val) from libsvm lines, by column expressions."""
    parts = spark.read.text(path).select(F.split("value", " ").alias("p"))
    pairs = F.transform(F.slice("p", F.lit(2), F.size("p")), lambda s: F.split(s, ":"))
    return parts.select(F.col("p")[0].cast("double").alias("y"), F.transform(pairs, lambda s: s[0].cast("int") - 1).alias("idx"), F.transform(pairs, lambda s: s[1].cast("double")).alias("val"))


def to_map(examples: DataFrame) -> DataFrame:
    return examples.withColumn("features", F.map_from_arrays("idx", "val"))


def to_vectors(examples: DataFrame, d: int) -> DataFrame:
    """(eid, label, features) for pyspark.ml; label 0 or 1."""
    from pyspark.ml.functions import array_to_vector

    if "x" in examples.columns:
        dense = F.col("x")
    else:
        slots = F.map_from_arrays("idx", "val")
        dense = F.transform(F.sequence(F.lit(0), F.lit(d - 1)), lambda j: F.coalesce(F.try_element_at(slots, j.cast("int")), F.lit(0.0)))
    return examples.select("eid", F.when(F.col("y") > 0, 1.0).otherwise(0.0).alias("label"), array_to_vector(dense).alias("features"))


def write_grouped(blocks: DataFrame, path: str) -> None:
    blocks.write.partitionBy("gid").parquet(path)


def write_bucketed(df: DataFrame, table: str, groups: int) -> None:
    """alpha or blocks as a table that joins by gid without an exchange."""
    df.write.bucketBy(groups, "gid").sortBy("bid").mode("overwrite").saveAsTable(table)


class _Range(InputPartition):
    def __init__(self, lo: int, hi: int):
        super().__init__(lo)
        self.lo, self.hi = lo, hi


class SyntheticReader(DataSourceReader):
    def __init__(self, options: dict):
        self.n, self.d, self.parts = int(options.get("n", 1000)), int(options.get("d", 10)), int(options.get("partitions", 4))

    def partitions(self) -> list[_Range]:
        return [_Range(k * self.n // self.parts, (k + 1) * self.n // self.parts) for k in range(self.parts)]

    def read(self, partition: _Range):
        import numpy as np

        teacher = (((37 * np.arange(self.d) + 11) % 19) - 9) / 9
        for eid in range(partition.lo, partition.hi):
            x = np.random.default_rng(eid).uniform(-1, 1, self.d)
            yield eid, 1.0 if float(x @ teacher) >= 0 else -1.0, x.tolist()


class SyntheticGlm(DataSource):
    """spark.read.format("synthetic_glm").option("n", ...).option("d", ...).load() after spark.dataSource.register(SyntheticGlm)."""

    @classmethod
    def name(cls) -> str:
        return "synthetic_glm"

    def schema(self) -> str:
        return "eid long, y double, x array<double>"

    def reader(self, schema) -> SyntheticReader:  # noqa: ANN001
        return SyntheticReader(self.options)
