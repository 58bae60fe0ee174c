"""Line dedup with levelled sorted runs of line hashes, in DataFrame functions only.

``LineRuns`` is a store of immutable runs: tables bucketed and sorted by (k1, k2), one file a bucket, that hold the number of
documents of one batch with the line. Each new batch is counted in as many partitions as a run has buckets and merge-anti-joined
with the runs that are there: keys that earlier runs already prove frequent are not written again; the others go to
a new run of level 0. When a level holds ``fan_out`` runs they are merged to one run of the next level. Runs are read in their order,
so neither the anti-join, nor the merging, nor the sums over all runs exchange or sort a run.
Keys are two 64-bit hashes of the stripped, A-Z lower-cased line.

Defined cases: a null text counts as one empty line; empty keys are never dropped; a document that
repeats a line counts once; rows that repeat a doc_id count as one document for the
counts and are rewritten one by one; all rows without an id count as one document; an empty table leaves the store as it is. Other columns pass
through ``drop_lines`` untouched, whatever their names; its two counts take names of their own only if asked for.
"""

from __future__ import annotations

import uuid

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from coordloom.llm.common import SPACE, ascii_lower, fits_broadcast, materialise, settings, shared_dir, text_or_empty

MIN_DOCS = 10
N_BATCHES = 4
RUN_SCHEMA = "k1 long, k2 long, n_docs long"
#: Frequent keys (16 bytes each) are broadcast up to this many, beyond it both sides are shuffled.
BROADCAST_KEYS = 200_000


def line_key(line):
    return ascii_lower(F.btrim(line, F.lit(SPACE)))


def _key_hashes(key):
    return F.xxhash64(key).alias("k1"), F.xxhash64(F.lit("line"), key).alias("k2")


def lines_of(docs: DataFrame, doc_id: str = "doc_id", text: str = "text") -> DataFrame:
    """(doc, k1, k2) of every line whose key isn't empty; one row for each document and key."""
    keys = F.explode(F.array_distinct(F.transform(F.split(text_or_empty(text), "\n", -1), line_key)))
    return docs.select(F.col(doc_id).alias("_doc"), keys.alias("_key")).filter("_key != ''").select("_doc", *_key_hashes(F.col("_key")))


#: Runs are joined, merged and summed as they lie: no session default may exchange or sort them again.
IN_PLACE = {
    "spark.sql.sources.bucketing.autoBucketedScan.enabled": "false",
    "spark.sql.legacy.bucketedTableScan.outputOrdering": "true",
    "spark.sql.unionOutputPartitioning": "true",
    "spark.sql.autoBroadcastJoinThreshold": "-1",
    "spark.sql.adaptive.autoBroadcastJoinThreshold": "-1",
}


class LineRuns:
    """Levelled runs in the shared folder. The list of runs is all that the driver keeps."""

    def __init__(self, spark: SparkSession, root: str | None = None, fan_out: int = 4, min_docs: int = MIN_DOCS, buckets: int | None = None):
        self.spark, self.root, self.fan_out, self.min_docs = spark, root or shared_dir(spark, "line-runs"), fan_out, min_docs
        self.buckets = buckets or int(spark.conf.get("spark.sql.shuffle.partitions"))
        self.levels: list[list[str]] = []
        self._written = 0

    def _write(self, frame: DataFrame, level: int) -> None:
        name = f"line_run_{uuid.uuid4().hex}"
        path = f"{self.root}/L{level}-{self._written:05d}"
        self._written += 1
        frame.write.bucketBy(self.buckets, "k1", "k2").sortBy("k1", "k2").option("path", path).saveAsTable(name)
        while len(self.levels) <= level:
            self.levels.append([])
        self.levels[level].append(name)

    def runs(self, level: int | None = None) -> DataFrame | None:
        out = None
        for name in (n for k, names in enumerate(self.levels) for n in names if level in (None, k)):
            run = self.spark.table(name)
            out = run if out is None else out.unionByName(run)
        return out

    def totals(self) -> DataFrame:
        runs = self.runs()
        return (runs if runs is not None else self.spark.createDataFrame([], RUN_SCHEMA)).groupBy("k1", "k2").agg(F.sum("n_docs").alias("n_docs"))

    def frequent(self) -> DataFrame:
        """Keys of ``min_docs`` documents or more, as a table."""
        with settings(self.spark, IN_PLACE):
            return materialise(self._frequent(), "frequent")

    def _frequent(self) -> DataFrame:
        return self.totals().filter(F.col("n_docs") >= self.min_docs).select("k1", "k2")

    def _fresh(self, lines: DataFrame) -> DataFrame:
        """What a batch adds: its counts, without the keys that are known to be frequent."""
        fresh = lines.dropDuplicates(["_doc", "k1", "k2"]).repartition(self.buckets, "k1", "k2").groupBy("k1", "k2").agg(F.count("*").alias("n_docs"))
        return fresh.join(self._frequent().hint("merge"), ["k1", "k2"], "left_anti") if any(self.levels) else fresh

    def add(self, lines: DataFrame) -> None:
        """Add one batch of (``_doc``, k1, k2); no document may come in two batches."""
        with settings(self.spark, IN_PLACE):
            self._write(self._fresh(lines), 0)
            self._compact()

    def unseen(self, lines: DataFrame) -> DataFrame:
        """Lines of a batch that no run holds: keeps the first batch's copy of each line (online use, before ``add``)."""
        runs = self.runs()
        return lines if runs is None else lines.join(runs.select("k1", "k2").hint("merge"), ["k1", "k2"], "left_anti")

    def _compact(self) -> None:
        level = 0
        while level < len(self.levels):
            if len(self.levels[level]) >= self.fan_out:
                merged, old = self.runs(level).groupBy("k1", "k2").agg(F.sum("n_docs").alias("n_docs")), self.levels[level]
                self._write(merged, level + 1)
                self.levels[level] = []
                for name in old:
                    self.spark.sql(f"DROP TABLE {name}")
            level += 1


def build_runs(docs: DataFrame, doc_id: str = "doc_id", text: str = "text", n_batches: int = N_BATCHES, min_docs: int = MIN_DOCS, fan_out: int = 4) -> LineRuns:
    """Feed a table to a new store in batches dealt by the hash of the document's id."""
    store = LineRuns(docs.sparkSession, fan_out=fan_out, min_docs=min_docs)
    batch = F.pmod(F.xxhash64(F.lit("batch"), F.col(doc_id)), F.lit(n_batches))
    for k in range(n_batches):
        store.add(lines_of(docs.filter(batch == k), doc_id, text))
    return store


def drop_lines(docs: DataFrame, store: LineRuns, doc_id: str = "doc_id", text: str = "text", counts: tuple[str, str] | None = None) -> DataFrame:
    """``docs`` with the text rewritten and, under the names in ``counts``, the number of lines before and of those dropped.

    The frequent keys of each document are gathered (none for most documents) and joined back by a
    key made of the row's id and text hash, so that equal rows stay apart only where they differ.
    """
    if counts and set(counts) & set(docs.columns):
        raise ValueError(f"the table has columns of its own called {sorted(set(counts) & set(docs.columns))}")
    frequent = store.frequent()
    small = fits_broadcast(frequent, BROADCAST_KEYS)
    packed = docs.select(
        F.struct(*[F.col(f"`{c}`") for c in docs.columns]).alias("_row"),
        F.xxhash64(F.col(f"`{doc_id}`"), F.col(f"`{text}`")).alias("_rid"),
    )
    keyed = lines_of(docs.select(F.xxhash64(F.col(f"`{doc_id}`"), F.col(f"`{text}`")).alias("_rid"), F.col(f"`{text}`").alias("_text")), "_rid", "_text")
    hits = keyed.join(F.broadcast(frequent) if small else frequent, ["k1", "k2"], "left_semi")
    per_row = hits.groupBy(F.col("_doc").alias("_rid")).agg(F.collect_set("k1").alias("_drop"))
    lines = F.split(text_or_empty(F.col(f"_row.`{text}`")), "\n", -1)
    joined = packed.join(per_row, "_rid", "left").select("_row", "_drop", lines.alias("_lines"))
    key1 = lambda x: F.xxhash64(line_key(x))
    kept = F.when(
        F.col("_drop").isNull(), F.col("_lines")
    ).otherwise(F.filter("_lines", lambda x: (line_key(x) == "") | ~F.array_contains("_drop", key1(x))))
    out = joined.select("_row", "_lines", kept.alias("_kept"))
    columns = [F.col(f"_row.`{c}`") if c != text else F.array_join("_kept", "\n").alias(text) for c in docs.columns]
    more = [F.size("_lines").cast("long").alias(counts[0]), (F.size("_lines") - F.size("_kept")).cast("long").alias(counts[1])] if counts else []
    return out.select(*columns, *more)
