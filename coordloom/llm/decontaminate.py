"""Benchmark decontamination with spaced-seed hashes, in DataFrame functions only.

Fixed masks select some of a few consecutive words; substitutions at the other positions leave a seed as it is.
Seeds of the benchmark and of the documents are joined by hash, and each (document, item, diagonal) that was hit is
verified along the whole diagonal. Items are of three kinds, each with masks that survive the substitutions it allows:

* ``LONG_ITEM`` words or more: three masks of 8 of 12 or 13 words. The best run with +1 for an equal and -2 for an unequal word must reach
  ``MIN_SCORE``, or half the words of an item of under twice as many.
* ``MIDDLE_ITEM`` to ``LONG_ITEM`` - 1 words: masks of 5 of 7 words; from 12 words on the run must reach more than half of the words.
* ``MIN_ITEM_WORDS`` to ``MIDDLE_ITEM`` - 1 words: masks of 3 of 4 words. Below 12 words a document has to hold the item whole, with one word
  replaced at most, or two in an item of 11; none in an item of five.

A part of an item that just reaches the score (half of its words in a row) may lie between all seeds of a kind and go unseen; whole copies and
those with the substitutions named above don't.

Items of fewer than ``MIN_ITEM_WORDS`` words ("the", "yes or no") are no evidence of a leak: any text may hold them, so they mark none. The
seeds of a kind are only made where the benchmark has items of it.

Defined cases: null or empty texts have no seeds; equal rows give one result;
null or repeated ids: rows are told apart by id and text, each with results (and dropped or kept) of its own; empty tables give empty results; other columns pass through ``drop_contaminated``,
whatever their names.
"""

from __future__ import annotations

from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

from coordloom.llm.common import fits_broadcast, materialise, text_or_empty

#: Word offsets of the three masks, put together from pairs one and two words apart; the last is the longest.
MASKS = ((0, 1, 3, 5, 6, 8, 10, 11), (0, 1, 3, 5, 6, 7, 9, 11), (0, 2, 4, 5, 7, 8, 10, 12))
SPANS = tuple(m[-1] + 1 for m in MASKS)
MIN_SCORE = 12
MIN_ITEM_WORDS = 5
MIDDLE_ITEM = 10
LONG_ITEM = 15
#: Masks of the shorter kinds: of every item at least one placement of one of them is free of any substitution that is allowed.
SHORT_MASKS = ((0, 1, 3), (0, 2, 3))
MIDDLE_MASKS = ((0, 1, 2, 4, 6), (0, 2, 4, 5, 6), (0, 1, 2, 3, 4))
#: Seeds, items and hits that are broadcast: at most so many rows.
BROADCAST_SEEDS = 400_000
BROADCAST_HITS = 200_000


def plain_words(text: Column) -> Column:
    """Lower-case runs of letters, marks and digits."""
    return F.filter(F.split(F.lower(text), r"[^\p{L}\p{M}\p{N}]+"), lambda w: w != "")


def _shift(a: Column, by: int, n: Column) -> Column:
    return F.slice(a, F.lit(by + 1), F.greatest(n, F.lit(1)))


def _pairs(a: Column, b: Column, apart: int, n: Column, salt: int | None = None) -> Column:
    extra = [] if salt is None else [F.lit(salt)]
    return F.zip_with(a, _shift(b, apart, n), lambda x, y: F.xxhash64(x, y, *extra))


def seeds(rows: DataFrame, keep: list[str]) -> DataFrame:
    """From ``keep`` and ``_w`` (words): one row per seed, (``keep``, pos, seed). The array steps are projections of their own, each done once."""
    n = F.col("_n")
    a = rows.select(*keep, F.size("_w").alias("_n"), F.transform("_w", lambda w: F.xxhash64(w)).alias("_h"))
    a = a.select(*keep, "_n", _pairs(F.col("_h"), F.col("_h"), 1, n).alias("_a1"), _pairs(F.col("_h"), F.col("_h"), 2, n).alias("_a2"))
    a = a.select(*keep, "_n", _pairs(F.col("_a1"), F.col("_a2"), 3, n).alias("_z1"), _pairs(F.col("_a2"), F.col("_a1"), 4, n).alias("_z2"))
    masked = (_pairs(F.col("_z1"), F.col("_z2"), 6, n, 0), _pairs(F.col("_z1"), F.col("_z1"), 6, n, 1), _pairs(F.col("_z2"), F.col("_z1"), 7, n, 2))
    # all three parts have n - 12 seeds, so that mask and place follow from the index
    part = F.greatest(n - (max(SPANS) - 1), F.lit(0))
    extra = F.when(n >= SPANS[0], F.slice(masked[0], F.greatest(n - 11, F.lit(1)), F.lit(1))).otherwise(F.array().cast("array<bigint>"))
    a = a.select(*keep, part.alias("_m"), F.concat(*[F.slice(m, F.lit(1), part) for m in masked], extra).alias("_s"))
    flat = a.select(*keep, "_m", F.posexplode_outer("_s").alias("_i", "seed")).filter("seed is not null")  # the outer form keeps the optimiser from copying all of the above into a filter on its size
    return flat.select(*keep, F.when(F.col("_i") == 3 * F.col("_m"), F.col("_m")).otherwise(F.col("_i") % F.greatest("_m", F.lit(1))).cast("int").alias("pos"), "seed")


def masked_seeds(rows: DataFrame, keep: list[str], masks: tuple[tuple[int, ...], ...]) -> DataFrame:
    """Like ``seeds`` for any masks: (``keep``, pos, seed)."""
    n = F.col("_n")
    hashed = rows.select(*keep, F.size("_w").alias("_n"), F.transform("_w", lambda w: F.xxhash64(w)).alias("_h"))

    def of(number: int, mask: tuple[int, ...]) -> Column:
        # whole arrays, shifted and hashed together: an index into _h inside a lambda would make all of _h again for every word
        joint = F.zip_with("_h", _shift(F.col("_h"), mask[1], n), lambda x, y: F.xxhash64(F.lit(number), x, y))
        for offset in mask[2:]:
            joint = F.zip_with(joint, _shift(F.col("_h"), offset, n), lambda x, y: F.xxhash64(x, y))
        return F.transform(F.slice(joint, F.lit(1), F.greatest(n - mask[-1], F.lit(0))), lambda s, i: F.struct(i.alias("pos"), s.alias("seed")))

    found = hashed.select(*keep, F.concat(*[of(k, m) for k, m in enumerate(masks)]).alias("_s"))
    return found.select(*keep, F.explode("_s").alias("_s")).select(*keep, "_s.pos", "_s.seed")


def _score(equal: Column) -> Column:
    """Best sum of a run of +1 (true) and -2 (false)."""
    start = F.struct(F.lit(0).alias("now"), F.lit(0).alias("best"))

    def step(acc: Column, e: Column) -> Column:
        now = F.greatest(F.lit(0), acc["now"] + F.when(e, F.lit(1)).otherwise(F.lit(-2)))
        return F.struct(now.alias("now"), F.greatest(acc["best"], now).alias("best"))

    return F.aggregate(equal, start, step, lambda acc: acc["best"])


def _row(name: str, key: str) -> tuple[Column, Column]:
    """The id and, as it may be null or repeat, a hash of the text."""
    return F.col(name), F.xxhash64("text").alias(key)


def _join(a: DataFrame, b: DataFrame, name: str, key: str, how: str = "inner") -> DataFrame:
    """Equal ids (null too) and keys; ``b``'s copies of both columns go."""
    b = b.withColumnsRenamed({name: "_b_id", key: "_b_key"})
    return a.join(b, F.col(name).eqNullSafe(F.col("_b_id")) & (F.col(key) == F.col("_b_key")), how).drop("_b_id", "_b_key")


def overlaps(docs: DataFrame, benchmark: DataFrame, min_score: int = MIN_SCORE) -> DataFrame:
    """(doc_id, item_id, score, n_equal, doc_first, n_compared): verified overlaps, the best of each document and item."""
    return _verified(docs, benchmark, min_score).drop("_doc", "_key")


def _verified(docs: DataFrame, benchmark: DataFrame, min_score: int) -> DataFrame:
    """``overlaps`` with the key of the document's row. Rows are told apart by id and text, so that ids may be null or repeat."""
    words = docs.select(*_row("doc_id", "_doc"), plain_words(text_or_empty("text")).alias("_w"))
    items = benchmark.select(*_row("item_id", "_key"), plain_words(text_or_empty("text")).alias("_w")).filter(F.size("_w") >= MIN_ITEM_WORDS).distinct()
    few_items, size = fits_broadcast(items, BROADCAST_SEEDS), F.size("_w")
    kinds = (
        (items.filter(size >= LONG_ITEM), seeds),
        (items.filter((size >= MIDDLE_ITEM) & (size < LONG_ITEM)), lambda rows, keep: masked_seeds(rows, keep, MIDDLE_MASKS)),
        (items.filter(size < MIDDLE_ITEM), lambda rows, keep: masked_seeds(rows, keep, SHORT_MASKS)),
    )
    hits = None
    for some, make in kinds:
        if not some.limit(1).count():
            continue
        tests = make(some, ["item_id", "_key"]).select("item_id", "_key", F.col("pos").alias("item_pos"), "seed")
        small = fits_broadcast(tests, BROADCAST_SEEDS)
        found = make(words, ["doc_id", "_doc"]).join(F.broadcast(tests) if small else tests, "seed").select("doc_id", "_doc", "item_id", "_key", (F.col("pos") - F.col("item_pos")).alias("diagonal"))
        hits = found if hits is None else hits.unionByName(found)
    if hits is None:
        hits = _join(words, items.select(F.col("item_id").alias("doc_id"), F.col("_key").alias("_doc"), "item_id", "_key"), "doc_id", "_doc").select("doc_id", "_doc", "item_id", "_key", F.lit(0).alias("diagonal"))  # no items: no rows
    per_doc = materialise(hits.distinct().groupBy("doc_id", "_doc").agg(F.collect_list(F.struct("item_id", "_key", "diagonal")).alias("_hits")), "seed-hits")
    few_hits = fits_broadcast(per_doc, BROADCAST_HITS)
    texts = _join(docs.select(*_row("doc_id", "_doc"), "text"), F.broadcast(per_doc) if few_hits else per_doc, "doc_id", "_doc")
    texts = texts.select("doc_id", "_doc", "_hits", plain_words(text_or_empty("text")).alias("_w"))
    longest = items.agg(F.max(F.size("_w"))).first()[0] or 0
    cut = F.transform("_hits", lambda h: F.struct(h["item_id"].alias("item_id"), h["_key"].alias("_key"), h["diagonal"].alias("diagonal"), F.slice(F.col("_w"), F.greatest(h["diagonal"], F.lit(0)) + 1, F.lit(longest)).alias("words")))
    cases = texts.select("doc_id", "_doc", F.explode(cut).alias("c")).select("doc_id", "_doc", "c.*")
    known = items.withColumnRenamed("_w", "_item")
    cases = _join(cases, F.broadcast(known) if few_items else known, "item_id", "_key")
    item = F.slice("_item", F.greatest(-F.col("diagonal"), F.lit(0)) + 1, F.greatest(F.size("_item"), F.lit(1)))
    equal = F.zip_with(item, F.slice("words", F.lit(1), F.size(item)), lambda x, y: F.coalesce(x == y, F.lit(False)))
    scored = cases.select("doc_id", "_doc", "item_id", "_key", F.size("_item").alias("item_words"), F.greatest("diagonal", F.lit(0)).alias("doc_first"), equal.alias("_e"))
    scored = scored.select("doc_id", "_doc", "item_id", "_key", "item_words", "doc_first", _score(F.col("_e")).alias("score"), F.size(F.filter("_e", lambda e: e)).alias("n_equal"), F.size("_e").alias("n_compared"))
    n = F.col("item_words")
    missing = F.when(n > MIDDLE_ITEM, 2).when(n > MIN_ITEM_WORDS, 1).otherwise(0)
    good = scored.filter(F.when(n < MIN_SCORE, F.col("n_equal") >= n - missing).otherwise(F.col("score") >= F.least(F.lit(min_score), F.when(n < LONG_ITEM, F.floor(n / 2) + 1).otherwise(F.ceil(n / 2)))))
    best = F.max(F.struct("score", "n_equal", (-F.col("doc_first")).alias("minus_first"), "n_compared")).alias("b")
    return good.groupBy("doc_id", "_doc", "item_id", "_key").agg(best).select("doc_id", "_doc", "item_id", "_key", F.col("b.score").cast("long").alias("score"), F.col("b.n_equal").cast("long").alias("n_equal"), (-F.col("b.minus_first")).cast("long").alias("doc_first"), F.col("b.n_compared").cast("long").alias("n_compared"))


def drop_contaminated(docs: DataFrame, benchmark: DataFrame) -> DataFrame:
    found = materialise(_verified(docs.select("doc_id", "text"), benchmark.select("item_id", "text"), MIN_SCORE).select("doc_id", "_doc").distinct(), "contaminated")
    packed = docs.select(F.struct(*[F.col(f"`{c}`") for c in docs.columns]).alias("_all"), *_row("doc_id", "_doc"))
    clean = _join(packed, F.broadcast(found) if fits_broadcast(found, BROADCAST_HITS) else found, "doc_id", "_doc", "left_anti")
    return clean.select(*[F.col(f"_all.`{c}`") for c in docs.columns])
