"""A corpus pipeline of five stages over ``documents``: quality rules, line dedup, near duplicates, decontamination, mixing.

Each stage takes all that its predecessor kept. The first four give back the columns of ``documents``; the last gives the mixture's digest.
"""

from __future__ import annotations

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from coordloom.llm import decontaminate, jaccard_join, line_dedup, mixing, quality_rules
from coordloom.llm.common import materialise


def quality(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """Documents that pass the policy stay as they are."""
    return quality_rules.filter_documents(docs, quality_rules.POLICIES["v1"])


def lines(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """Lines of ten documents or more go; ``n_chars`` follows the text."""
    out = line_dedup.drop_lines(docs, line_dedup.build_runs(docs))
    changed = out.withColumn("n_chars", F.when(F.col("text").isNotNull(), F.length("text")).cast("long"))
    return changed.select(docs.columns)


def near_duplicates(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """Of each group of near copies the row with the smallest id stays, once; one without an id only if none has one."""
    if not docs.groupBy("doc_id").count().filter("count > 1 or doc_id is null").limit(1).count():
        labels = jaccard_join.jaccard_components(docs).filter("doc_id = component_id").select("doc_id")
        return docs.join(labels, "doc_id", "left_semi").select(docs.columns)
    rows = materialise(docs.withColumn("_row", F.monotonically_increasing_id()), "rows")
    labels = jaccard_join.jaccard_components(rows, "_row").select(F.col("doc_id").alias("_row"), "component_id")
    first = F.min(F.struct(F.col("doc_id").isNull(), "doc_id", "_row"))["_row"]
    firsts = rows.join(rows.select("_row", "doc_id").join(labels, "_row").groupBy("component_id").agg(first.alias("_row")), "_row", "left_semi")
    named = firsts.filter("doc_id is not null").dropDuplicates(["doc_id", "text"])  # equal rows with one id are copies too, however short
    return named.unionByName(firsts.filter("doc_id is null")).select(docs.columns)


def decontamination(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """Documents that hold a benchmark passage go."""
    return decontaminate.drop_contaminated(docs, spark.read.parquet(f"{sf_dir}/benchmark.parquet"))


def mixture(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """How much of each document the mixture takes."""
    return mixing.Mix(docs).taken()


STAGES = [("quality rules", quality), ("line dedup", lines), ("n-gram Jaccard join", near_duplicates), ("benchmark decontamination", decontamination), ("mixing sources to target weights", mixture)]

#: SQL has no closed form for the components of the third stage; tests compare the run with brute force.
ORACLE_SQL = None


def run(spark: SparkSession, sf_dir: str) -> DataFrame:
    docs = spark.read.parquet(f"{sf_dir}/documents.parquet")
    for k, (name, stage) in enumerate(STAGES):
        docs = stage(spark, docs, sf_dir)
        if k + 1 < len(STAGES):
            docs = materialise(docs, "stage-" + name.replace(" ", "-"))
    return docs
