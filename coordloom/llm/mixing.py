"""Mixing sources to target weights with a multivariate-hypergeometric splitting tree.

Documents are cut into blocks of at most ``BLOCK_WORDS`` words. A source's quota of words gives whole
passes over its blocks and a part of one more pass, in an order that is permuted anew for each pass.
A binary tree over the output shards splits the vector of block quotas: at each node the left half
draws its share without replacement, so that every source's blocks are used up exactly at the leaves.
A shard takes the next blocks of each source's permuted sequence (disjoint ranges) and shuffles them locally.

What a document gives to the mix is the sum of the draws of all shards; a block that no shard draws isn't taken. The plan (one
row per source, up to ``MAX_SOURCES``, and sources times shards counts) is made on the driver; blocks never
leave the executors. Ranks come from two levels of 4096 hash buckets, so that no window holds a whole source. The number of shards
follows from the words (``SHARD_WORDS`` each, ``N_SHARDS`` at least).

Defined cases: null text has size 0 and is never taken; a null source is one source, last in order;
rows that repeat an id (null ids among them) are numbered by source, size and text and mixed one by one; equal rows are interchangeable;
an empty table gives empty results; other columns aren't read, whatever their names.
"""

from __future__ import annotations

import hashlib
import math
from dataclasses import dataclass

import numpy as np
from pyspark.sql import Column, DataFrame, Window
from pyspark.sql import functions as F

from coordloom.llm.common import SPACE_RUN, SPACE, materialise, text_or_empty

BLOCK_WORDS = 256
N_SHARDS = 64
SHARD_WORDS = 200_000_000
#: Sources that the driver plans for; a table with more has to be grouped into fewer first.
MAX_SOURCES = 1_000_000
#: Cells of the plan's tables that are broadcast; larger ones are joined.
BROADCAST_ROWS = 200_000
MAX_REPEATS = 3
SEED = 17
LEVEL_BITS = 12
#: Above this many blocks numpy's exact sampler stops; the rounded normal law with the same mean and variance takes over.
EXACT_LIMIT = 1_000_000_000


def n_words(text: Column) -> Column:
    trimmed = F.btrim(text, F.lit(SPACE))
    return F.when(F.length(trimmed) == 0, F.lit(0)).otherwise(F.regexp_count(trimmed, F.lit(SPACE_RUN)) + 1).cast("long")


def water_fill(sizes: list[int], weights: list[int], max_repeats: int = MAX_REPEATS) -> list[float]:
    """Targets that share ``sum(sizes)`` by weight; none above ``max_repeats`` times its size, the excess goes to the others."""
    total, targets = sum(sizes), [0.0] * len(sizes)
    order = sorted(range(len(sizes)), key=lambda k: (max_repeats * sizes[k] / weights[k], k))
    left, weight = total, sum(weights)
    for n, k in enumerate(order):
        cap = max_repeats * sizes[k]
        if cap * weight < left * weights[k]:
            targets[k], left, weight = float(cap), left - cap, weight - weights[k]
        else:
            for j in order[n:]:
                targets[j] = (left * weights[j]) / weight
            break
    return targets


def _draw(rng: np.random.Generator, good: int, bad: int, sample: int) -> int:
    low, high = max(0, sample - bad), min(good, sample)
    if low == high:
        return low
    if good + bad < EXACT_LIMIT:
        return int(rng.hypergeometric(good, bad, sample))
    n = good + bad
    mean = sample * (good / n)
    spread = math.sqrt(max(0.0, mean * (bad / n) * ((n - sample) / (n - 1))))
    return min(high, max(low, round(rng.normal(mean, spread))))


def _node_rng(seed: int, first: int, last: int) -> np.random.Generator:
    return np.random.default_rng(int.from_bytes(hashlib.sha256(f"{seed}:{first}:{last}".encode()).digest()[:8], "big"))


def splitting_tree(quotas: list[int], n_shards: int, seed: int = SEED) -> list[list[int]]:
    """counts[shard][source]: every column sums to its quota, every row to its shard's even share of all blocks."""
    out: list[list[int]] = [[] for _ in range(n_shards)]
    todo = [(0, n_shards, list(quotas))]
    while todo:
        first, last, have = todo.pop()
        if last - first == 1:
            out[first] = have
            continue
        middle, total = (first + last) // 2, sum(have)
        take = total * (middle - first) // (last - first)
        rng, left, rest, need = _node_rng(seed, first, last), [], total, take
        for q in have:  # one conditional univariate draw per source
            x = _draw(rng, q, rest - q, need)
            left.append(x)
            rest, need = rest - q, need - x
        todo += [(first, middle, left), (middle, last, [a - b for a, b in zip(have, left, strict=True)])]
    return out


@dataclass(frozen=True)
class SourcePlan:
    source: str | None
    weight: int
    size: int
    n_blocks: int
    target: float
    quota: int

    @property
    def passes(self) -> int:
        return self.quota // self.size if self.size else 0

    @property
    def rest(self) -> int:
        return self.quota - self.passes * self.size


def plan_sources(rows: list, max_repeats: int = MAX_REPEATS, weights: dict | None = None) -> list[SourcePlan]:
    """``rows``: (source, size, n_blocks) in the order of sources."""
    w = [(weights or {}).get(r[0], k % 3 + 1) for k, r in enumerate(rows)]
    targets = water_fill([r[1] for r in rows], w, max_repeats)
    return [SourcePlan(r[0], a, r[1], r[2], t, min(max_repeats * r[1], math.floor(t + 0.5))) for r, a, t in zip(rows, w, targets, strict=True)]


def sized(docs: DataFrame, keep: tuple[str, ...] = ()) -> DataFrame:
    """(doc_id, source, size, _row) per input row; ``_row`` numbers rows that share an id. Rows without an id are numbered in groups of equal text, apart by its hash."""
    flat = docs.select("doc_id", "source", n_words(text_or_empty("text")).alias("size"), F.xxhash64("text").alias("_h"), *keep)
    # a null id is spread by the text: its rows' numbers only have to differ, so they start from the hash
    apart = F.when(F.col("doc_id").isNull(), F.col("_h"))
    number = F.row_number().over(Window.partitionBy("doc_id", apart).orderBy("source", "size", "_h")).cast("string")
    return flat.withColumn("_row", F.when(F.col("doc_id").isNull(), F.concat_ws("/", F.col("_h"), number)).otherwise(number)).drop("_h")


def _key(seed: int) -> Column:
    text = F.concat_ws(":", F.lit(seed), F.coalesce(F.col("doc_id").cast("string"), F.lit("-")), F.col("_row"), F.col("block"), F.col("pass"))
    return F.conv(F.substring(F.md5(text), 1, 15), 16, 10).cast("long")


class Mix:
    """A planned mixture: ``sources`` (driver), ``counts`` (shards times sources) and ``draws`` (DataFrame)."""

    def __init__(self, docs: DataFrame, n_shards: int | None = None, seed: int = SEED, block_words: int = BLOCK_WORDS, max_repeats: int = MAX_REPEATS, weights: dict | None = None):
        self.sizes, self.seed, self.block_words = materialise(sized(docs), "mix-sizes"), seed, block_words
        blocks = F.ceil(F.col("size") / block_words)
        stats = self.sizes.groupBy("source").agg(F.sum("size").cast("long").alias("size"), F.sum(blocks).cast("long").alias("n_blocks")).limit(MAX_SOURCES + 1).collect()
        if len(stats) > MAX_SOURCES:
            raise ValueError("too many sources for one plan; group them first")
        stats.sort(key=lambda r: (r["source"] is None, (r["source"] or "").encode()))
        self.sources = plan_sources([tuple(r) for r in stats], max_repeats, weights)
        self.n_shards = n_shards or max(N_SHARDS, -(-sum(p.quota for p in self.sources) // SHARD_WORDS))
        self._rank_blocks()

    def plan_frame(self) -> DataFrame:
        rows = [(p.source, p.size, p.target, p.passes, p.rest, k) for k, p in enumerate(self.sources)]
        return self.sizes.sparkSession.createDataFrame(rows, "source string, source_size long, target double, passes long, rest long, sid int")

    def _rank_blocks(self) -> None:
        """Every block of every pass in use, with its place in the source's sequence and the words taken from it."""
        b = self.block_words
        by_source = self._with_plan()
        passes = F.explode(F.sequence(F.lit(0), F.col("passes") - F.when(F.col("rest") > 0, F.lit(0)).otherwise(F.lit(1)))).alias("pass")
        draws = by_source.filter("size > 0 and (passes > 0 or rest > 0)").select("doc_id", "_row", "sid", "size", "passes", "rest", passes)
        draws = draws.select("*", F.explode(F.sequence(F.lit(0), F.ceil(F.col("size") / b) - 1)).alias("block"))
        draws = draws.withColumn("words", F.least(F.lit(b), F.col("size") - F.col("block") * b)).withColumn("key", _key(self.seed))
        top, low = 1 << (60 - LEVEL_BITS), 1 << (60 - 2 * LEVEL_BITS)
        draws = draws.withColumns({"b1": F.floor(F.col("key") / top).cast("int"), "b2": F.floor((F.col("key") % top) / low).cast("int")})
        second = draws.groupBy("sid", "pass", "b1", "b2").agg(F.sum("words").alias("w2"), F.count("*").alias("n2"))
        first = second.groupBy("sid", "pass", "b1").agg(F.sum("w2").alias("w1"), F.sum("n2").alias("n1"))
        before = lambda c, w: F.coalesce(F.sum(c).over(w.rowsBetween(Window.unboundedPreceding, -1)), F.lit(0))
        w1, w2 = Window.partitionBy("sid", "pass").orderBy("b1"), Window.partitionBy("sid", "pass", "b1").orderBy("b2")
        first = first.select("sid", "pass", "b1", before("w1", w1).alias("o1"), before("n1", w1).alias("m1"))
        second = second.select("sid", "pass", "b1", "b2", before("w2", w2).alias("o2"), before("n2", w2).alias("m2"))
        w3 = Window.partitionBy("sid", "pass", "b1", "b2").orderBy("key", "doc_id", "_row", "block")
        ranked = draws.select("*", before("words", w3).alias("o3"), (F.row_number().over(w3) - 1).alias("m3"))
        ranked = ranked.join(second, ["sid", "pass", "b1", "b2"]).join(first, ["sid", "pass", "b1"])
        start, place = F.col("o1") + F.col("o2") + F.col("o3"), F.col("m1") + F.col("m2") + F.col("m3")
        left = F.when(F.col("pass") < F.col("passes"), F.col("words")).otherwise(F.greatest(F.lit(0), F.least(F.col("words"), F.col("rest") - start)))
        ranked = ranked.select("doc_id", "_row", "sid", "pass", "block", "key", place.alias("place"), left.cast("long").alias("words")).filter("words > 0")
        self.ranked = materialise(ranked, "mix-blocks")

    def _with_plan(self) -> DataFrame:
        plan = self.plan_frame().withColumnRenamed("source", "_source")
        return self.sizes.join(F.broadcast(plan) if len(self.sources) <= BROADCAST_ROWS else plan, F.col("source").eqNullSafe(F.col("_source"))).drop("_source")

    def draws(self) -> DataFrame:
        """(doc_id, _row, pass, block, words, shard, rank): blocks dealt to shards by the tree, in their local shuffled order."""
        used = {r["sid"]: r["n"] for r in self.ranked.groupBy("sid").agg(F.count("*").alias("n")).collect()}  # a row per source
        quotas = [used.get(k, 0) for k in range(len(self.sources))]
        self.counts = splitting_tree(quotas, self.n_shards, self.seed)
        bounds, at = [], [0] * len(quotas)
        for shard, row in enumerate(self.counts):
            for k, n in enumerate(row):
                if n:
                    bounds.append((k, shard, at[k], at[k] + n))
                    at[k] += n
        spark = self.sizes.sparkSession
        small = lambda df, n: F.broadcast(df) if n <= BROADCAST_ROWS else df
        ends = spark.createDataFrame(bounds, "sid int, shard int, lo long, hi long").groupBy("sid").agg(F.sort_array(F.collect_list(F.struct("hi", "shard"))).alias("ends"))
        per_pass = spark.createDataFrame([(k, p.n_blocks) for k, p in enumerate(self.sources)], "sid int, per_pass long")
        dealt = self.ranked.join(small(per_pass, len(self.sources)), "sid").join(small(ends, len(bounds)), "sid")
        place = F.col("pass") * F.col("per_pass") + F.col("place")
        shard = F.try_element_at(F.filter("ends", lambda e: e["hi"] > place), F.lit(1))["shard"]
        dealt = dealt.select("doc_id", "_row", "sid", "pass", "block", "words", shard.alias("shard"), F.xxhash64(F.lit(self.seed), "key", "pass").alias("local_key"))
        return dealt.filter("shard is not null")  # drawn by a shard

    def shard_counts(self) -> DataFrame:
        """(shard, source, n_blocks, n_words): what the shards draw, counted from the draws; equals the tree's counts."""
        names = self.plan_frame().select("sid", "source")
        counted = self.draws().groupBy("shard", "sid").agg(F.count("*").alias("n_blocks"), F.sum("words").alias("n_words"))
        return counted.join(names, "sid").select("shard", "source", "n_blocks", "n_words")

    def taken(self) -> DataFrame:
        """One row per input row: size, its source's size and target, and the words that all shards take of it."""
        sums = self.draws().groupBy("doc_id", "_row").agg(F.sum("words").alias("taken")).select(F.col("doc_id").alias("_d"), F.col("_row").alias("_r"), "taken")
        sizes = self._with_plan()
        joined = sizes.join(sums, sizes["doc_id"].eqNullSafe(F.col("_d")) & (sizes["_row"] == F.col("_r")), "left")
        return joined.select("doc_id", "size", "source_size", "target", F.coalesce("taken", F.lit(0)).cast("long").alias("taken"))


def write_shards(mix: Mix, docs: DataFrame, path: str) -> None:
    """Write the mixed blocks as text, one folder per shard, each in its locally shuffled order: files follow one another by name. A shard
    is cut into ranges of its order, so that its size is bound by no task."""
    words = F.split(F.btrim(text_or_empty("text"), F.lit(SPACE)), SPACE_RUN)
    numbered = sized(docs, ("text",)).select(F.col("doc_id").alias("_d"), F.col("_row").alias("_r"), "source", words.alias("_w"))
    joined = mix.draws().join(numbered, F.col("_d").eqNullSafe(F.col("doc_id")) & (F.col("_r") == F.col("_row")))
    piece = F.array_join(F.slice("_w", (F.col("block") * mix.block_words + 1).cast("int"), F.col("words").cast("int")), " ")
    rows = joined.select("shard", "local_key", "doc_id", "source", "pass", "block", piece.alias("text"))
    rows.repartitionByRange("shard", "local_key").sortWithinPartitions("shard", "local_key").write.partitionBy("shard").parquet(path)
