"""Quality rules as a bitmask ledger, in DataFrame functions only.

``ledger`` evaluates every rule once per document and stores one failure bit per rule beside the
measurements. Policies are (version, mask) pairs applied to the stored bits, so a new policy or an
ablation never reads a text again.

Defined cases: a null or empty text has no words, all measurements 0 and fails ``few_words``; rows
with equal ids are judged one by one; an empty table gives an empty ledger; other columns of the
input are ignored by ``ledger`` and kept by ``filter_documents``, which uses no name of its own in
the output.
"""

from __future__ import annotations

from dataclasses import dataclass

from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

from coordloom.llm.common import SPACE, text_or_empty, words_of

SYMBOLS = "#*$%&|<>"
WINDOW = 8
MIN_WORDS = 20
MAX_REPEAT_PERCENT = 30

#: One bit each, in this order; a rule's position never changes, new rules are appended.
RULES: tuple[tuple[str, str], ...] = (
    ("few_words", f"n_words < {MIN_WORDS}"),
    ("repeated_windows", f"100 * n_repeat_words > {MAX_REPEAT_PERCENT} * n_words"),
    ("short_words", "word_chars < 2 * n_words"),
    ("long_words", "word_chars > 16 * n_words"),
    ("many_symbols", "100 * n_symbols > 100 * n_words"),
    ("repeated_lines", "n_text_lines >= 4 and 100 * n_dup_lines > 60 * n_text_lines"),
    ("ellipsis_lines", "n_text_lines >= 4 and 100 * n_ellipsis_lines > 60 * n_text_lines"),
    ("bullet_lines", "n_text_lines >= 4 and 100 * n_bullet_lines > 95 * n_text_lines"),
)
BIT = {name: 1 << k for k, (name, _) in enumerate(RULES)}
BASE_MASK = BIT["few_words"] | BIT["repeated_windows"]


@dataclass(frozen=True)
class Policy:
    """Rejects a document that fails any rule in ``mask``."""

    version: str
    mask: int


POLICIES = {
    "base": Policy("base", BASE_MASK),
    "v1": Policy("v1", sum(BIT.values())),
    "no_layout": Policy("no_layout", BASE_MASK | BIT["short_words"] | BIT["long_words"] | BIT["many_symbols"]),
}


def _repeats(frame: DataFrame, rest: list[str]) -> DataFrame:
    """``n_repeat_words`` from the window hashes ``_h``; only rows with a repeated hash get past the first step."""
    many = lambda c: F.greatest(F.size(c), F.lit(1))
    placed = F.when(F.size(F.array_distinct("_h")) < F.size("_h"), F.sort_array(F.transform("_h", lambda h, i: F.struct(h.alias("h"), i.alias("i")))))
    frame = frame.select(*rest, placed.alias("_p"))
    twins = F.zip_with("_p", F.slice("_p", F.lit(2), many("_p")), lambda a, b: F.when(a["h"] == b["h"], F.array(a["i"], b["i"])).otherwise(F.array().cast("array<int>")))
    frame = frame.select(*rest, F.sort_array(F.array_distinct(F.flatten(twins))).alias("_s"))
    gaps = F.zip_with("_s", F.slice("_s", F.lit(2), many("_s")), lambda a, b: F.least(F.coalesce(b - a, F.lit(WINDOW)), F.lit(WINDOW)))
    covered = F.when(F.col("_s").isNull(), F.lit(0)).otherwise(F.aggregate(gaps, F.lit(0), lambda acc, g: acc + g))
    return frame.select(*rest, covered.cast("long").alias("n_repeat_words"))


def _joined(hashes: Column, apart: int, n: Column) -> Column:
    """Hashes of spans twice as long: element i takes in element i + ``apart``. The last ones, without a partner, are cut off later."""
    return F.zip_with(hashes, F.slice(hashes, F.lit(apart + 1), F.greatest(n, F.lit(1))), lambda a, b: F.xxhash64(a, b))


def measure(docs: DataFrame, text: str = "text", keep: tuple[str, ...] = ("doc_id",)) -> DataFrame:
    """The measurements per document, without any shuffle; ``keep`` columns pass through."""
    raw = docs.select(*keep, text_or_empty(text).alias("_t"))
    split = raw.select(*keep, "_t", words_of(F.col("_t")).alias("_w"), F.filter(F.split("_t", "\n", -1), lambda x: F.length(F.btrim(x, F.lit(SPACE))) > 0).alias("_l"))
    plain = F.col("_t")
    for symbol in SYMBOLS:
        plain = F.replace(plain, F.lit(symbol), F.lit(""))
    n = F.col("n_words")
    counted = split.select(
        *keep,
        F.size("_w").alias("n_words"),
        F.length(F.array_join("_w", "")).cast("long").alias("word_chars"),
        (F.length("_t") - F.length(plain)).cast("long").alias("n_symbols"),
        F.size("_l").cast("long").alias("n_text_lines"),
        (F.size("_l") - F.size(F.array_distinct("_l"))).cast("long").alias("n_dup_lines"),
        F.size(F.filter("_l", lambda x: F.rtrim(x).endswith("...") | F.rtrim(x).endswith("…"))).cast("long").alias("n_ellipsis_lines"),
        F.size(F.filter("_l", lambda x: F.substring(F.ltrim(x), 1, 1).isin("-", "*", "•"))).cast("long").alias("n_bullet_lines"),
        F.transform("_w", lambda w: F.xxhash64(w)).alias("_h"),
    )
    rest = [c for c in counted.columns if c != "_h"]
    for span in (1, 2, 4):  # each step is a projection of its own, so that no array is computed twice
        counted = counted.select(*rest, _joined(F.col("_h"), span, n).alias("_h"))
    windows = F.when(n >= WINDOW, F.slice("_h", F.lit(1), F.greatest(n - (WINDOW - 1), F.lit(1)))).otherwise(F.array().cast("array<bigint>"))
    counted = counted.select(*rest, windows.alias("_h"))
    return _repeats(counted, rest).withColumn("n_words", n.cast("long"))


def ledger(docs: DataFrame, text: str = "text", keep: tuple[str, ...] = ("doc_id",)) -> DataFrame:
    """``measure`` plus ``fail_bits``: the sum of the bits of the rules that the document fails."""
    bits = sum((F.when(F.expr(rule), F.lit(1 << k)).otherwise(F.lit(0)) for k, (_, rule) in enumerate(RULES)), F.lit(0))
    return measure(docs, text, keep).withColumn("fail_bits", bits.cast("long"))


def apply_policy(book: DataFrame, policy: Policy) -> DataFrame:
    failed = F.col("fail_bits").bitwiseAND(F.lit(policy.mask))
    return book.withColumns({"kept": failed == 0, "base_failed": F.col("fail_bits").bitwiseAND(F.lit(BASE_MASK)) != 0, "policy": F.lit(policy.version)})


def ablate(book: DataFrame, policy: Policy) -> DataFrame:
    """Per rule of the policy: documents failing it, failing only it (which dropping it would bring back), and the pass totals."""
    failed = F.col("fail_bits").bitwiseAND(F.lit(policy.mask))
    used = [(name, BIT[name]) for name, _ in RULES if BIT[name] & policy.mask]
    sums = [F.count("*").alias("n_docs"), F.count_if(failed == 0).alias("n_kept"), F.bit_or(failed).alias("bits_seen")]
    for name, bit in used:
        sums += [F.count_if(failed.bitwiseAND(F.lit(bit)) != 0).alias(f"f_{name}"), F.count_if(failed == bit).alias(f"o_{name}")]
    total = book.agg(*sums)
    rows = F.explode(F.array(*[F.struct(F.lit(name).alias("rule"), F.col(f"f_{name}").alias("n_failed"), F.col(f"o_{name}").alias("n_only")) for name, _ in used]))
    return total.select("n_docs", "n_kept", rows.alias("r")).select("r.rule", "r.n_failed", "r.n_only", "n_docs", "n_kept", (F.col("n_kept") + F.col("r.n_only")).alias("n_kept_without"))


def filter_documents(docs: DataFrame, policy: Policy, text: str = "text") -> DataFrame:
    """The documents that pass, with their own columns only; they live under one struct beside the rule columns.

    The filter uses a running number, which the optimiser may not compute elsewhere: else it would push the filter
    below the measurements, with a copy of all their expressions for every mention of one.
    """
    packed = docs.select(F.struct(*[F.col(f"`{c}`") for c in docs.columns]).alias("_row"), F.col(f"`{text}`").alias("_text"))
    judged = apply_policy(ledger(packed, "_text", ("_row",)), policy)
    judged = judged.select("_row", "kept", F.monotonically_increasing_id().alias("_at"))
    return judged.filter("kept and _at >= 0").select("_row.*")
