"""Operators against brute force, round trips and edge cases."""

import hashlib
import random
import re
from collections import Counter, defaultdict

import numpy as np
import pytest
from pyspark.sql import functions as F

from coordloom.llm import chat_format, decontaminate, hashing, html_blocks, html_labeller, jaccard_join, license_scan, line_dedup, mixing, quality_rules, queries, recompression, warc

WORD = re.compile(r"[^\x20\x09-\x0D]+")
LOWER = str.maketrans("ABCDEFGHIJKLMNOPQRSTUVWXYZ", "abcdefghijklmnopqrstuvwxyz")
SCHEMA = "doc_id long, text string, lang string, source string, n_chars long"


def docs_of(spark, texts):
    return spark.createDataFrame([(i, t, "en", s, None if t is None else len(t)) for i, t, s in ((k, t, f"s{k % 3}") if not isinstance(t, tuple) else t for k, t in enumerate(texts))], SCHEMA)


def corpus(seed=1, n=60):
    """Words from a small set; copies, near copies, shared passages, runs, odd white space, null, empty, long."""
    rng = random.Random(seed)
    vocabulary = ["".join(rng.choices("abcdeé", k=rng.randint(1, 5))) for _ in range(400)]
    words = lambda k: rng.choices(vocabulary, k=k)
    passage = words(80)
    texts = []
    for k in range(n):
        w = words(rng.choice((0, 1, 3, 5, 30, 120, 300)))
        if k % 4 == 0:
            cut = rng.randint(0, 30)
            w = w[: len(w) // 2] + passage[cut : cut + rng.randint(40, 50 + 20)] + w[len(w) // 2 :]
        if k % 9 == 0:
            w += [rng.choice("ab")] * rng.choice((3, 55, 120))
        texts.append("".join(x + rng.choice((" ", " ", "\n", "\t ")) for x in w))
    for k in range(0, n, 5):
        texts.append(texts[k])
        w = texts[k].split(" ")
        for _ in range(2):
            w[rng.randrange(len(w))] = "zzz"
        texts.append(" ".join(w))
    return [*texts, None, "", "   \n ", "Mixed CASE Words here İstanbul", " ".join(words(6000))]


def shingles(text):
    w = WORD.findall((text or "").translate(LOWER))
    return {tuple(w[k : k + 5]) for k in range(len(w) - 4)} if len(w) >= 5 else {tuple(w)} if w else set()


def jaccard_brute(texts):
    sets, parent = {i: shingles(t) for i, t in texts.items()}, {i: i for i in texts}

    def find(x):
        while parent[x] != x:
            x = parent[x]
        return x

    inverted = defaultdict(list)
    for i in sorted(sets):
        for j, c in Counter(j for g in sets[i] for j in inverted[g]).items():
            if 100 * c >= 80 * (len(sets[i]) + len(sets[j]) - c):
                a, b = find(i), find(j)
                parent[max(a, b)] = min(a, b)
        for g in sets[i]:
            inverted[g].append(i)
    return {i: (len(sets[i]), find(i)) for i in sets}


def repeats_brute(texts, window=50):
    words, first = {i: WORD.findall(t or "") for i, t in texts.items()}, {}
    for i in sorted(words):
        for k in range(len(words[i]) - window + 1):
            first.setdefault(tuple(words[i][k : k + window]), i)
    out = {}
    for i, w in words.items():
        gone = set()
        for k in range(len(w) - window + 1):
            if first[tuple(w[k : k + window])] < i:
                gone |= set(range(k, k + window))
        out[i] = (len(w), len(gone), " ".join(x for k, x in enumerate(w) if k not in gone))
    return out


@pytest.fixture(scope="module")
def texts():
    return corpus()


def test_hashes_follow_words(texts):
    import pyarrow as pa

    words, bounds = hashing.word_hashes(pa.array(texts, pa.string()), lower=True)
    seen = {}
    for t, a, b in zip(texts, bounds[:-1], bounds[1:], strict=True):
        w = WORD.findall((t or "").translate(LOWER))
        assert len(w) == b - a
        for x, h in zip(w, words[a:b].tolist(), strict=True):
            assert seen.setdefault(x, h) == h
    assert len(set(seen.values())) == len(seen)
    sliced, _ = hashing.word_hashes(pa.array(["x", *texts], pa.string()).slice(1), lower=True)
    assert np.array_equal(sliced, words)


def test_jaccard_join(spark, texts):
    got = {r["doc_id"]: (r["n_shingles"], r["component_id"]) for r in jaccard_join.jaccard_components(docs_of(spark, texts)).collect()}
    assert got == jaccard_brute(dict(enumerate(texts)))


def test_jaccard_join_large_near_group(spark):
    """A group of near copies, some just under the limit: blocks and bands are used, no link is lost."""
    rng = random.Random(5)
    base = [f"w{k}" for k in range(120)]
    texts = []
    for k in range(150):
        w = list(base)
        for _ in range(rng.choice((0, 1, 2, 3, 4, 5))):
            w[rng.randrange(120)] = f"x{rng.randrange(10**6)}"
        texts.append(" ".join(w))
    got = {r["doc_id"]: (r["n_shingles"], r["component_id"]) for r in jaccard_join.jaccard_components(docs_of(spark, texts)).collect()}
    assert got == jaccard_brute(dict(enumerate(texts)))


def test_pairs_need_their_matches_before_sets_are_compared(spark, monkeypatch):
    """Counting is exact in any slicing of the tokens, and pairs under min(l, l') are never compared; with the counts broken links are lost."""
    rng = np.random.default_rng(4)
    prefixes = [np.unique(rng.integers(0, 60, rng.integers(0, 40))) for _ in range(30)]
    want = np.array([[len(np.intersect1d(a, b)) for b in prefixes[10:]] for a in prefixes[:10]])
    for columns in (7, 1 << 14):
        monkeypatch.setattr(jaccard_join, "COLUMNS", columns)
        assert np.array_equal(jaccard_join.shared_prefix_tokens(prefixes, np.arange(10), np.arange(10, 30)), want)
    number = (0, False, 0)
    row = lambda node, tokens, matches, prefix: (1, number, number, 0, False, node, len(tokens), tokens, matches, prefix)
    schema = "pivot long, i struct<band:int,linked:boolean,part:long>, j struct<band:int,linked:boolean,part:long>, side int, linked boolean, node long, n long, tokens array<long>, matches int, prefix array<long>"
    same = list(range(20))
    found = lambda rows: [tuple(r) for r in jaccard_join.block_links(spark.createDataFrame(rows, schema)).collect()]
    assert found([row(1, same, 2, [1, 2]), row(2, same, 3, [1, 2, 3])]) == [(1, 2)]
    assert found([row(1, same, 2, [1, 5]), row(2, same, 3, [1, 2, 3])]) == []


def test_jaccard_join_blocks_bound_tokens(spark, texts, monkeypatch):
    """Blocks so small that every group is cut: the result is the same."""
    monkeypatch.setattr(jaccard_join, "BLOCK", 3)
    monkeypatch.setattr(jaccard_join, "BLOCK_TOKENS", 500)
    got = {r["doc_id"]: (r["n_shingles"], r["component_id"]) for r in jaccard_join.jaccard_components(docs_of(spark, texts)).collect()}
    assert got == jaccard_brute(dict(enumerate(texts)))


def test_jaccard_join_hot_classes(spark, texts, monkeypatch):
    monkeypatch.setattr(jaccard_join, "HOT_ROWS", 2)
    many = [*texts, *[texts[3]] * 9, *[""] * 5]
    for limit in (10, 0):
        monkeypatch.setattr(jaccard_join, "HOT_CLASSES", limit)
        docs = docs_of(spark, many).withColumn("n", F.lit(1)).withColumn("label", F.lit("x")).withColumn("token", F.lit(2))
        got = {r["doc_id"]: (r["n_shingles"], r["component_id"]) for r in jaccard_join.jaccard_components(docs).collect()}
        assert got == jaccard_brute(dict(enumerate(many)))


def test_jaccard_join_null_ids_and_long_texts(spark):
    long = " ".join(f"l{k % 70000}" for k in range(120_000))
    near = long[:-6] + " end"
    rows = jaccard_join.jaccard_components(docs_of(spark, [(None, long, "s"), (7, near, "s"), (None, "", "s"), (9, None, "s")])).collect()
    assert sorted(((r["doc_id"], r["component_id"]) for r in rows), key=str) == [(7, 7), (9, 9), (None, 7), (None, None)]


def test_jaccard_join_repeated_ids(spark):
    a, b = " ".join(f"a{k}" for k in range(30)), " ".join(f"b{k}" for k in range(30))
    rows = jaccard_join.jaccard_components(docs_of(spark, [(1, a, "s"), (1, b, "s"), (2, a, "s"), (3, b, "s"), (4, "", "s")])).collect()
    assert sorted((r["doc_id"], r["component_id"]) for r in rows) == [(1, 1), (1, 1), (2, 1), (3, 1), (4, 4)]


def test_prefix_lengths_are_safe():
    for n in range(1, 60):
        for m in range(n, 75):
            need = -(-80 * (n + m) // 180)  # least intersection at 0.8
            for l in (1, 2, 5):
                if need >= l and need <= n:
                    # the smallest possible shared part of two l-prefixes in one order
                    assert n - jaccard_join.prefix_length(n, l) <= need - l or jaccard_join.prefix_length(n, l) == n


def test_recompression(spark, texts):
    got = {r["doc_id"]: (r["n_words"], r["n_removed"], r["kept"]) for r in recompression.remove_repeats(docs_of(spark, texts)).collect()}
    assert got == repeats_brute(dict(enumerate(texts)))


def _thue_morse(n, a, b):
    x, y = a, b
    for _ in range(n):
        x, y = x + y, y + x
    return x, y


def test_words_that_cancel_out_in_polynomials_are_told_apart(spark):
    """Two different words of 1,024 letters before the same 49 words: no window repeats, nothing goes."""
    x, y = _thue_morse(9, "ab", "ba")
    tail = " ".join(f"w{k}" for k in range(49))
    rows = recompression.remove_repeats(docs_of(spark, [f"{x} {tail}", f"{y} {tail}"])).collect()
    assert [r["n_removed"] for r in rows] == [0, 0]
    assert len({int(h) for h in hashing.word_hashes(__import__("pyarrow").array([f"{x} {y} {x * 3} {y * 3}"]), False)[0]}) == 4


def test_words_are_compared_before_anything_goes(spark):
    """A claim that a witness's words don't bear out is found, and its passage stays."""
    a, b = ([f"{x}{k}".encode() for k in range(60)] for x in "ab")
    text = lambda w: b" ".join(w).decode()
    known = recompression.packed_texts(spark.createDataFrame([(0, text(a))], "id long, text string"))
    claim = lambda words: (0, recompression._tag(a), 0, 2, recompression._digest(words[:51]))
    bad = [tuple(r) for r in recompression._refuted(spark.createDataFrame([claim(a), claim(b)], recompression.CLAIM), known, 50).collect()]
    assert [(*r[:4], bytes(r[4])) for r in bad] == [claim(b)]
    starts = [(recompression._tag(b), k, 0, recompression._tag(a), k) for k in range(2)]
    notes = spark.createDataFrame([(7, None, starts)], "id long, copies array<int>, starts array<struct<tag:int,start:int,w_id:long,w_tag:int,w_start:int>>")
    rows = recompression.packed_texts(spark.createDataFrame([(7, text(b))], "id long, text string")).join(notes, "id").select("z", "id", "copies", "starts")
    assert recompression._kept(rows, 50, set()).first()["n_removed"] == 51
    assert recompression._kept(rows, 50, {claim(b)}).first()["n_removed"] == 0


def test_passages_join_neighbouring_windows():
    row = lambda start, w, at: {"tag": 1, "start": start, "w_id": w, "w_tag": 5, "w_start": at}
    assert recompression._passages([row(3, 0, 10), row(2, 0, 9), row(4, 1, 11), row(9, 0, 16), {**row(5, 1, 12), "tag": 2}], 1) == [(2, 2, 0, 5, 9), (4, 1, 1, 5, 11), (9, 1, 0, 5, 16)]


def test_recompression_ids(spark):
    """Null and repeated ids, clashing columns."""
    p = " ".join(f"p{k}" for k in range(60))
    q = " ".join(f"q{k}" for k in range(60))
    docs = docs_of(spark, [(None, f"{p} a", "s"), (None, f"b {p}", "s"), (4, f"c {p}", "s"), (4, q, "s"), (4, f"{q} d", "s"), (5, f"e {q}", "s")])
    docs = docs.withColumn("id", F.lit("x")).withColumn("hits", F.lit(1)).withColumn("starts", F.lit(2)).withColumn("n", F.lit(3)).withColumn("kept", F.lit(4))
    got = sorted((r["n_removed"], r["kept"].split(" ")[0]) for r in recompression.remove_repeats(docs).collect())
    assert got == [(0, "b"), (0, "p0"), (0, "q0"), (0, "q0"), (60, "c"), (60, "e")]


def test_equal_windows_share_an_anchor():
    rng = np.random.default_rng(3)
    for trial in range(300):
        pool = rng.integers(1, 1 << 62, rng.choice((1, 2, 3, 50)), dtype=np.uint64)
        window = rng.choice(pool, 50)
        found = []
        for _ in range(2):
            left, right = rng.choice(pool, rng.integers(0, 40)), rng.choice(pool, rng.integers(0, 40))
            words = np.concatenate([left, window, right])
            ends = np.zeros(len(words), bool)
            ends[-1] = True
            names, start, span = recompression.parse(words, ends)
            name, _, first, length = recompression.anchors(names, start, span, np.zeros(len(names), int))
            inside = (first >= len(left)) & (first + length <= len(left) + 50)
            found.append({(a, f - len(left)) for a, f in zip(name[inside].tolist(), first[inside].tolist(), strict=True)})
        assert found[0] & found[1], trial


def test_line_dedup(spark, texts):
    lines = [f"Common  line \t{'' if k % 2 else ' '}\nown {k}\n\n{'COMMON  LINE' if k % 3 else 'rare'}" for k in range(25)] + texts
    docs = docs_of(spark, lines)
    out = line_dedup.drop_lines(docs, line_dedup.build_runs(docs), counts=("n_lines", "n_dropped")).collect()
    key = lambda x: x.strip(" \t\n\x0b\f\r").translate(LOWER)
    count = Counter(k for t in lines for k in {key(x) for x in (t or "").split("\n")} if k)
    for r in out:
        parts = (lines[r["doc_id"]] or "").split("\n")
        kept = [x for x in parts if count[key(x)] < 10]
        assert (r["n_lines"], r["n_dropped"], r["text"]) == (len(parts), len(parts) - len(kept), "\n".join(kept))


def test_line_dedup_keeps_clashing_columns(spark):
    """Columns with the names that the operator and its stage use stay as they are; null and repeated ids."""
    import corpus_pipeline as cp

    rows = [(k, f"shared\nown {k}", "s") for k in range(10)] + [(None, "shared\nnull a", "s"), (None, "shared\nnull b", "s"), (3, "shared\nagain", "s")]
    names = ("n_lines", "n_dropped", "_row", "_rid", "_doc", "_key", "k1", "k2", "_drop", "_lines", "_kept", "_text")
    docs = docs_of(spark, rows)
    for k, name in enumerate(names):
        docs = docs.withColumn(name, F.lit(k))
    out = cp.lines(spark, docs, "")
    assert out.columns == docs.columns
    got = out.collect()
    assert sorted(r["text"] for r in got) == sorted(t.split("\n")[1] for _, t, _ in rows) and all([r[n] for n in names] == list(range(len(names))) for r in got)
    few = docs_of(spark, [(None, "shared\nx", "s")] * 12)
    assert {r["text"] for r in line_dedup.drop_lines(few, line_dedup.build_runs(few)).collect()} == {"shared\nx"}


def test_runs_are_neither_exchanged_nor_sorted(spark):
    """The anti-join of a batch, the merging and the sums read the runs as they lie: only the batch itself is exchanged."""
    store = line_dedup.LineRuns(spark, fan_out=9, min_docs=2)
    for k in range(3):
        store.add(line_dedup.lines_of(docs_of(spark, [(10 * k, f"always\nonly {k}", "s")])))
    with line_dedup.settings(spark, line_dedup.IN_PLACE | {"spark.sql.adaptive.enabled": "false"}):
        sums = store.totals()._jdf.queryExecution().executedPlan().toString()
        assert "Exchange" not in sums and sums.count("Bucketed: true") == 3
        batch = store._fresh(spark.range(5).select(F.col("id").alias("_doc"), F.col("id").alias("k1"), F.col("id").alias("k2")))
        join = batch._jdf.queryExecution().executedPlan().toString()
        right = join[join.index("SortMergeJoin") :]
        assert join.count("Exchange hashpartitioning") == 2 and right.index("Exchange") < right.index("Bucketed: true") and "Exchange" not in right[right.index("Bucketed: true") :]


def test_line_runs_compact_and_anti_join(spark):
    store = line_dedup.LineRuns(spark, fan_out=2, min_docs=2)
    for k in range(4):
        store.add(line_dedup.lines_of(docs_of(spark, [(10 * k, f"always\nonly {k}", "s"), (10 * k + 1, f"pair {k // 2}", "s")])))
    assert len(store.levels) >= 3 and sum(map(len, store.levels)) == 1
    assert store.frequent().count() == 3
    fresh = line_dedup.lines_of(docs_of(spark, [(99, "always\nnew", "s")]))
    assert store.unseen(fresh).count() == 1


def rules_brute(text):
    t = text or ""
    w = WORD.findall(t)
    seen = Counter(tuple(w[k : k + 8]) for k in range(len(w) - 7))
    covered = {k + j for k in range(len(w) - 7) if seen[tuple(w[k : k + 8])] > 1 for j in range(8)}
    lines = [x for x in t.split("\n") if WORD.search(x)]
    return len(w), sum(map(len, w)), sum(c in "#*$%&|<>" for c in t), len(lines) - len(set(lines)), len(covered)


def test_quality_rules(spark, texts):
    book = quality_rules.apply_policy(quality_rules.ledger(docs_of(spark, [*texts, "a b c " * 40, "x\nx\ny # $"])), quality_rules.POLICIES["v1"])
    for r in book.collect():
        t = [*texts, "a b c " * 40, "x\nx\ny # $"][r["doc_id"]]
        want = rules_brute(t)
        assert (r["n_words"], r["word_chars"], r["n_symbols"], r["n_dup_lines"], r["n_repeat_words"]) == want
        assert r["base_failed"] == (want[0] < 20 or 100 * want[4] > 30 * want[0]) and not (r["base_failed"] and r["kept"])


def test_ablation_adds_up(spark, texts):
    policy = quality_rules.POLICIES["v1"]
    book = quality_rules.ledger(docs_of(spark, texts))
    kept = quality_rules.apply_policy(book, policy).filter("kept").count()
    for r in quality_rules.ablate(book, policy).collect():
        without = quality_rules.Policy("x", policy.mask & ~quality_rules.BIT[r["rule"]])
        assert r["n_kept"] == kept and r["n_kept_without"] == quality_rules.apply_policy(book, without).filter("kept").count()


def test_filter_keeps_clashing_columns(spark):
    docs = docs_of(spark, ["word " * 5, " ".join(f"w{k}" for k in range(40))]).withColumn("n_words", F.lit("mine")).withColumn("_h", F.lit(1))
    out = quality_rules.filter_documents(docs, quality_rules.POLICIES["v1"]).collect()
    assert [(r["doc_id"], r["n_words"], r["_h"]) for r in out] == [(1, "mine", 1)]


def test_license_scan(spark):
    texts = ["x MIT-License y\nApache License, Version 2.0 mit license", None, "", "GNU General Public License v3 or later", "é mit licenseé", "nothing"]
    rows = {r["doc_id"]: r for r in license_scan.scan_licenses(docs_of(spark, texts)).collect()}
    assert (rows[0]["n_words"], rows[0]["n_base"], rows[0]["first_word"], rows[0]["last_word"], rows[0]["base_labels"]) == (11, 3, 1, 9, "apache,mit")
    assert "apache-2.0" in rows[0]["labels"].split(",") and 0 < rows[0]["score"] <= 1
    assert rows[1]["n_words"] == rows[2]["n_words"] == 0 and rows[2]["score"] == 0.0 and rows[1]["first_word"] is None
    assert rows[3]["base_labels"] == "gpl" and "gpl-3" in rows[3]["labels"]
    assert rows[4]["n_base"] == 0 and rows[5]["labels"] == ""


def _example(pattern):
    """A short text that a rule's pattern matches."""
    p = re.sub(r"\.\{1,80\}\?", "x", pattern)
    p = re.sub(r"\[([^\]])[^\]]*\]", r"\1", p)
    while True:
        q = re.sub(r"\(\?:((?:[^()|]|\|)*)\)\??", lambda m: m[1].split("|")[0], p)
        if q == p:
            break
        p = q
    return re.sub(r"(.)\?", r"\1", p)


def test_no_gate_hides_a_match():
    scanner = license_scan.Scanner()
    assert len(license_scan.rules()) >= 300
    for rule in license_scan.rules():
        text = _example(rule.pattern)
        assert re.search(rule.pattern, text), rule
        assert rule.keyword in text, rule
        assert scanner.scan(f"a {text} b".encode())[7] > 0, rule


def test_gates_come_from_the_book():
    rule = license_scan.Rule("z", "zed", "zebra", "zebra (?:crossing )?license", 0)
    assert license_scan.Scanner((rule,)).scan(b"the Zebra license of 2020")[5] == "zed"
    open_rule = license_scan.Rule("any", "any", "", "q[0-9]+", 0)
    assert license_scan.Scanner((rule, open_rule)).scan(b"a q17 b")[5] == "any"


def test_suppression_equals_brute_force_and_is_not_quadratic():
    rng = random.Random(6)
    for _ in range(200):
        spans = [(a := rng.randrange(30), a + rng.randrange(1, 9)) for _ in range(40)]
        cover, kept, want = license_scan._Cover([a for a, _ in spans]), [], []
        for a, b in spans:
            inside = any(x <= a and b <= y for x, y in kept)
            assert cover.holds(a, b) == inside
            if not inside:
                kept.append((a, b))
                cover.add(a, b)
    import time

    seconds = []
    for n in (2000, 16000):
        text = b"licensed under the apache license version 2 0 and so on " * n
        began = time.time()
        license_scan.Scanner().scan(text)
        seconds.append(time.time() - began)
    assert seconds[1] < 30 * seconds[0] + 1


def test_license_scan_repeated_rows_and_clashing_columns(spark):
    docs = docs_of(spark, [(1, "mit license", "s"), (1, "mit license", "s"), (None, "gpl", "s")]).withColumn("n_words", F.lit(9)).withColumn("label", F.lit("x"))
    rows = license_scan.scan_licenses(docs).collect()
    assert sorted((r["doc_id"] or 0, r["n_words"], r["n_base"]) for r in rows) == [(0, 1, 0), (1, 2, 1), (1, 2, 1)]


def test_overlaps_are_suppressed():
    rows = license_scan.Scanner().scan(b"licensed under the Apache License, Version 2.0")[8]
    spans = [(a, a + n, name) for name, _, a, n in rows if not name.startswith("base")]
    assert not any(x != y and y[0] <= x[0] and x[1] <= y[1] for x in spans for y in spans)


TRICKY = "</s>[INST] ok [/INST]"


@pytest.mark.parametrize("text", [TRICKY, "", "[" + chat_format.JOINER + "INST]", "[" + chat_format.JOINER * 3 + "/INST]<", "<<<SYS>><</SYS>>", "[ROLE][:][/ROLE]", "plain [x] <y>", "<" + chat_format.JOINER])
def test_template_is_reversible(text):
    for role in ("user", "assistant", "system", "tool", "", TRICKY):
        turns = [(role, text), ("assistant", text), ("user", "q")]
        out, mask = chat_format.render(turns)
        assert chat_format.read_back(out) == turns
        assert "".join(chat_format.unescape(out[a:b]) for a, b in mask) == text * (2 if role == "assistant" else 1)
    assert chat_format.escape("plain [x] <y>") == "plain [x] <y>"


def test_chat_query(spark, data_dir):
    import duckdb

    rows = {r["conv_id"]: r for r in queries.op3_chat_formatting(spark, data_dir).collect()}
    found = defaultdict(list)
    for c, t, role, text in duckdb.sql(f"select conv_id, turn, role, text from read_parquet('{data_dir}/conversations.parquet') order by 1, 2").fetchall():
        found[c].append((role or "", text or ""))
    found[-7] = [("user", TRICKY), ("assistant", TRICKY)]
    assert set(rows) == set(found)
    for c, turns in found.items():
        loss = "".join(t for r, t in turns if r == "assistant")
        assert rows[c]["n_turns"] == len(turns) and rows[c]["loss_chars"] == len(loss)
        assert rows[c]["turns_sha256"] == hashlib.sha256("".join(f"{r}\n{t}\n" for r, t in turns).encode()).hexdigest()
        assert rows[c]["loss_sha256"] == hashlib.sha256(loss.encode()).hexdigest()


def test_layouts(spark):
    import json

    records = [
        {"prompt": "p", "response": "r"}, {"instruction": "i", "input": "x", "output": "o"}, {"messages": [{"role": "user", "content": "a"}, {"role": "assistant", "content": "b"}]}, {"messages": [{"role": "user", "content": [{"type": "text", "text": "a"}]}, {"role": "assistant", "content": [{"type": "text", "text": "b"}]}]},
        {"system": "s", "conversations": [{"from": "human", "value": "a"}, {"from": "gpt", "value": "b"}]}, {"chat": {"messages": [{"author": {"role": "user"}, "text": "a"}]}}, {"what": 1},
    ]
    df = spark.createDataFrame([(k, json.dumps(r)) for k, r in enumerate(records)] + [(7, "{broken"), (8, None)], "conv_id long, record string")
    got = defaultdict(list)
    for r in chat_format.mapped_records(df).orderBy("conv_id", "turn").collect():
        got[r["conv_id"]].append((r["layout"], r["role"], r["text"]))
    assert [x[1:] for x in got[0]] == [("user", "p"), ("assistant", "r")] and got[1][0] == ("instruction", "user", "i\n\nx")
    assert [x[1:] for x in got[2]] == [x[1:] for x in got[3]] == [("user", "a"), ("assistant", "b")]
    assert [x[1] for x in got[4]] == ["system", "user", "assistant"] and got[5][0][0] == "nested-chat"
    assert all(got[k][0][0] is None for k in (6, 7, 8))
    assert {r["conv_id"] for r in chat_format.unmapped(df).collect()} == {6, 7, 8}
    assert {r["conv_id"] for r in chat_format.format_turns(chat_format.turns_from_json(df)).collect()} == set(range(6))
    assert chat_format.format_turns(chat_format.mapped_records(df)).count() == 6
    ids = spark.createDataFrame([(1152921504606846977, '{"prompt": "p", "response": "r"}'), (None, '{"prompt": "p", "response": "r"}'), (-5, "{")], "conv_id long, record string")
    assert {r["conv_id"] for r in chat_format.mapped_records(ids).collect()} == {1152921504606846977, None, -5}


def test_chat_edge_cases(spark):
    """Null texts and roles, ties of turns, null turns and ids, clashing columns."""
    rows = [(1, 0, "user", "b"), (1, 0, "user", "a"), (1, 0, None, None), (1, None, "system", "first"), (None, 0, "user", "x"), (None, 1, "assistant", None)]
    table = spark.createDataFrame(rows, chat_format.TURNS).withColumn("turns", F.lit(1)).withColumn("formatted", F.lit("x")).withColumn("layout", F.lit(2))
    out = {r["conv_id"]: chat_format.read_back(r["formatted"]) for r in chat_format.format_turns(chat_format.turns_from_table(table)).collect()}
    assert out == {1: [("system", "first"), ("", ""), ("user", "a"), ("user", "b")], None: [("user", "x"), ("assistant", "")]}


def test_mixing(spark, texts):
    docs = docs_of(spark, [*texts, (5, "same id here", "s1"), (900, "a b c d", None)])
    mix = mixing.Mix(docs, n_shards=8, block_words=16)
    rows = mix.taken().collect()
    assert len(rows) == docs.count()
    size, target, taken = defaultdict(int), {}, defaultdict(int)
    for r in rows:
        k = r["source_size"], round(r["target"], 6)
        size[k] += r["size"]
        target[k] = r["target"]
        taken[k] += r["taken"]
        assert 0 <= r["taken"] <= 3 * r["size"]
    for k in size:
        assert abs(taken[k] - target[k]) <= 1 and target[k] <= 3 * k[0] + 1e-6
    assert abs(sum(p.target for p in mix.sources) - sum(p.size for p in mix.sources)) < 1e-6
    again = {(r["doc_id"], r["size"]): r["taken"] for r in mixing.Mix(docs, n_shards=8, block_words=16).taken().collect()}
    assert again == {(r["doc_id"], r["size"]): r["taken"] for r in rows}


def test_what_is_taken_comes_through_the_tree(spark, texts, monkeypatch):
    """The draws follow the tree's counts shard by shard; a tree that loses a shard loses what it would have drawn."""
    docs = docs_of(spark, texts).withColumn("_h", F.lit(1)).withColumn("_row", F.lit(2)).withColumn("size", F.lit(3)).withColumn("shard", F.lit(4))
    mix = mixing.Mix(docs, n_shards=8, block_words=16)
    drawn = {(r["shard"], r["source"]): (r["n_blocks"], r["n_words"]) for r in mix.shard_counts().collect()}
    tree = {(k, p.source): n for k, row in enumerate(mix.counts) for p, n in zip(mix.sources, row, strict=True) if n}
    assert {k: n for k, (n, _) in drawn.items()} == tree
    before = sum(r["taken"] for r in mix.taken().collect())
    assert before == sum(w for _, w in drawn.values())
    whole = mixing.splitting_tree
    monkeypatch.setattr(mixing, "splitting_tree", lambda quotas, n, seed: [[0] * len(quotas) if k == n - 1 else row for k, row in enumerate(whole(quotas, n, seed))])
    after = sum(r["taken"] for r in mix.taken().collect())
    lost = sum(n for (k, _), n in tree.items() if k == 7)
    assert 0 < before - after and sum(r["n_blocks"] for r in mix.shard_counts().collect()) == sum(tree.values()) - lost


def test_write_shards(spark, texts, tmp_path):
    docs = docs_of(spark, [*texts[:20], (None, "n1 n2 n3", "s1"), (None, "n4 n5", "s1"), (3, "same id", "s2")])
    mix = mixing.Mix(docs, n_shards=4, block_words=8)
    mixing.write_shards(mix, docs, f"file://{tmp_path}/mix")
    back = spark.read.parquet(f"file://{tmp_path}/mix").collect()
    assert Counter(r["shard"] for r in back) == Counter({k: sum(row) for k, row in enumerate(mix.counts) if sum(row)})
    assert sum(len(WORD.findall(r["text"])) for r in back) == sum(r["taken"] for r in mix.taken().collect())
    assert mixing.Mix(docs).n_shards == mixing.N_SHARDS


def test_splitting_tree_is_exact_and_unbiased():
    quotas = [100, 7, 0, 900]
    totals = np.zeros((8, 4))
    for seed in range(60):
        counts = np.array(mixing.splitting_tree(quotas, 8, seed))
        assert counts.sum(axis=0).tolist() == quotas and counts.min() >= 0
        assert counts.sum(axis=1).max() - counts.sum(axis=1).min() <= 1
        totals += counts
    assert np.allclose(totals / 60, np.array(quotas) / 8, atol=6)
    big = mixing.splitting_tree([10**12, 10**11], 4)
    assert sum(r[0] for r in big) == 10**12 and sum(r[1] for r in big) == 10**11


def test_water_filling():
    assert mixing.water_fill([100, 100, 100], [1, 2, 3]) == [50, 100, 150]
    t = mixing.water_fill([10, 1000, 10], [1, 2, 3])
    assert t[0] == 30 and t[2] == 30 and t[1] == pytest.approx(960)
    assert mixing.water_fill([0, 0], [1, 2]) == [0, 0] and mixing.water_fill([], []) == []


def test_decontamination(spark):
    rng = random.Random(2)
    words = lambda k: [f"t{rng.randrange(5000)}" for _ in range(k)]
    items = [words(30) for _ in range(5)] + [words(6)]
    swapped = list(items[1])
    swapped[4], swapped[15], swapped[24] = "q1", "q2", "q3"
    docs = [words(50), words(20) + items[0] + words(20), words(10) + swapped + words(10), items[2][5:20], words(9) + items[5] + words(9), None, "", items[3][:8] + words(40), items[4] * 3]
    texts = [d if d is None or isinstance(d, str) else " ".join(d).upper() for d in docs]
    bench = spark.createDataFrame([(k, ", ".join(w)) for k, w in enumerate(items)] + [(9, None), (10, "")], "item_id long, text string")
    found = {(r["doc_id"], r["item_id"]): r for r in decontaminate.overlaps(docs_of(spark, texts), bench).collect()}
    assert set(found) == {(1, 0), (2, 1), (3, 2), (4, 5), (8, 4)}
    assert found[2, 1]["n_equal"] == 27 and found[1, 0]["doc_first"] == 20
    kept = {r["doc_id"] for r in decontaminate.drop_contaminated(docs_of(spark, texts), bench).collect()}
    assert kept == {0, 5, 6, 7}


def overlap_brute(texts, items):
    """Every diagonal of every document and item by the rules of the docstring, without seeds."""
    words = lambda t: [w for w in re.split(r"[\W_]+", (t or "").lower()) if w]
    found = set()
    for d, text in texts.items():
        for i, item in items.items():
            w, v = words(text), words(item)
            n = len(v)
            for shift in range(-n + 1, len(w)) if n >= decontaminate.MIN_ITEM_WORDS else ():
                equal = [v[k] == w[k + shift] for k in range(n) if 0 <= k + shift < len(w)]
                score = best = 0
                for e in equal:
                    score = max(0, score + (1 if e else -2))
                    best = max(best, score)
                if (sum(equal) >= n - (2 if n > 10 else 1 if n > 5 else 0)) if n < 12 else best >= (n // 2 + 1 if n < decontaminate.LONG_ITEM else min(12, -(-n // 2))):
                    found.add((d, i))
                    break
    return found


def test_decontamination_against_brute_force(spark):
    """Items of every length from 1 to 20, whole, with words replaced at every place, cut at the ends of documents, under hot and short items."""
    rng = random.Random(9)
    words = lambda k: [f"t{rng.randrange(3000)}" for _ in range(k)]
    items = {n: words(n) for n in range(1, 21)}
    texts = {}
    for n, item in items.items():
        for place in range(n):
            texts[1000 * n + place] = " ".join(words(7) + [w if k != place else "other" for k, w in enumerate(item)] + words(7))
        texts[1000 * n + 50] = " ".join(words(5) + item + words(5))
        texts[1000 * n + 51] = " ".join(item[: n // 2] + words(20))
        texts[1000 * n + 52] = " ".join(words(9) + item[: n - n // 4])
        if n >= 11:
            two = [w if k not in (2, n - 3) else "other" for k, w in enumerate(item)]
            texts[1000 * n + 53] = " ".join(words(3) + two + words(3))
    docs = docs_of(spark, [(k, t, "s") for k, t in texts.items()])
    bench = spark.createDataFrame([(n, " ".join(w)) for n, w in items.items()], "item_id long, text string")
    got = {(r["doc_id"], r["item_id"]) for r in decontaminate.overlaps(docs, bench).collect()}
    want = overlap_brute(texts, {n: " ".join(w) for n, w in items.items()})
    halves = {(d, i) for d, i in want if d % 1000 == 51}  # parts at the very limit of the score: seeds may miss them
    assert got <= want and want - halves <= got
    assert all((1000 * n + place, n) in got for n in range(6, 21) for place in range(n)) and not any(i < 5 for _, i in got)


def test_tiny_items_mark_nothing(spark):
    docs = docs_of(spark, [f"the cat {k} sat on the mat" for k in range(20)])
    bench = spark.createDataFrame([(0, "the"), (1, "sat on"), (2, "on the mat")], "item_id long, text string")
    assert decontaminate.overlaps(docs, bench).count() == 0
    clash = docs.withColumn("_doc", F.lit(1)).withColumn("_hits", F.lit(2)).withColumn("item_id", F.lit(3))
    kept = decontaminate.drop_contaminated(clash, bench)
    assert kept.columns == clash.columns and kept.count() == 20


def test_seeds_follow_their_masks(spark):
    w = [f"w{k}" for k in range(40)]
    df = spark.createDataFrame([(0, w), (1, w[:12]), (2, w[:11])], "k long, _w array<string>")
    found = {(r["k"], r["seed"]): r["pos"] for r in decontaminate.seeds(df, ["k"]).collect()}
    assert Counter(k for k, _ in found) == {0: 3 * 28 + 1, 1: 1}
    for m in decontaminate.MASKS:
        changed = [x if k in m or k > m[-1] else f"other{k}" for k, x in enumerate(w)]
        other = {r["seed"] for r in decontaminate.seeds(spark.createDataFrame([(0, changed)], "k long, _w array<string>"), ["k"]).filter("pos = 0").collect()}
        assert any(p == 0 and s in other for (k, s), p in found.items() if k == 0)


def test_html(spark):
    source = '<html><head><title>T</title><script>var t="</p><article>no";</script></head><body><nav><ul><li><a href="/x">Menu</a></li></ul></nav><div class="ad">Buy it.</div><article><h1>The  title &amp; more</h1><p><b>First<br>paragraph of&nbsp;it.<br><p>Second one with some more words in it.</p></article><div class="comments"><p>Nice one.</p></div><footer>&copy; x</footer>'
    pages = spark.createDataFrame([(1, "u", source), (2, None, None), (3, "v", ""), (4, "w", "<p"), (1, "u", source)], "page_id long, url string, html string")
    rows = html_labeller.extract_main_text(pages).orderBy("page_id").collect()
    assert len(rows) == 5 and rows[0]["text"] == rows[1]["text"] == "The title & more\nFirst paragraph of it.\nSecond one with some more words in it."
    assert rows[0]["n_chars"] == len(rows[0]["text"]) and [r["text"] for r in rows[2:4]] == ["", ""]


def test_labeller_on_held_out_pages():
    model, rng = html_labeller.trained(), random.Random(12345)
    data = [html_labeller.labelled(html_labeller.sample_page(rng)) for _ in range(150)]
    right = [((p >= 0.5) == (y >= 0.5)) for (_, y), p in zip(data, model.label([x for x, _ in data]), strict=True)]
    assert np.concatenate(right).mean() > 0.99 and np.mean([r.all() for r in right]) > 0.93


def _foreign_page(rng):
    """Pages of another generator than the training one: other class names, tables, bare containers."""
    mark = "\x01"
    sentence = lambda a, b: html_labeller._sentence(rng, rng.randint(a, b))
    paragraph = lambda: " ".join(sentence(6, 25) for _ in range(rng.randint(2, 6)))
    nav = "".join(f'<span><a href="/{w}">{w}</a></span> | ' for w in html_labeller._words(rng, 6))
    body = f"<h1>{mark}{sentence(3, 9)}</h1>" + "".join(rng.choice((f"<p>{mark}{paragraph()}</p>", f"<p>{mark}{paragraph()}</p>", f"<h3>{mark}{sentence(2, 5)}</h3>", f"<blockquote>{mark}{sentence(5, 20)}</blockquote>")) for _ in range(rng.randint(2, 12)))
    foot = f'<div class="colophon">&copy; 2020 {sentence(2, 5)} <a href="/p">{sentence(1, 2)}</a></div>'
    read = "".join(f'<li><a href="/{w}">{sentence(3, 6)}</a></li>' for w in html_labeller._words(rng, 4))
    return "<html><body>" + rng.choice((
        f'<div class="masthead">{nav}</div><div class="story-content">{body}</div><div class="most-read"><ul>{read}</ul></div>{foot}', f"<table width=100%><tr><td valign=top>{nav}</td><td>{body}</td></tr></table>{foot}",
        f'<div id="hd">{nav}</div><div id="bd"><div class="yui-main">{body}</div></div>{foot}', f'<nav>{nav}</nav><main role="main"><div class="longform">{body}</div></main><aside><p>{sentence(3, 8)}</p></aside>{foot}',
    ))


def test_labeller_on_pages_of_another_generator():
    rng = random.Random(777)
    data = [html_labeller.labelled(_foreign_page(rng)) for _ in range(200)]
    found = np.concatenate(html_labeller.trained().label([x for x, _ in data])) >= 0.5
    true = np.concatenate([y for _, y in data]) >= 0.5
    assert (found & true).sum() >= 0.95 * true.sum() and (found & true).sum() >= 0.95 * found.sum()


def test_html_very_long_pages(spark):
    page = "<body><nav><a href=/>m</a></nav><article><h1>Title here.</h1>" + "<p>Some words of a paragraph, one after the other.</p>" * 20_000 + "</article></body>"
    rows = html_labeller.extract_main_text(spark.createDataFrame([(1, "u", page)], "page_id long, url string, html string").withColumn("text", F.lit(1))).collect()
    assert rows[0]["n_blocks"] == 20_002 and rows[0]["n_main"] == 20_001


def test_labeller_gradient():
    rng = np.random.default_rng(0)
    m = html_labeller.Labeller(rng)
    m.w = {k: v.astype(np.float64) for k, v in m.w.items()}
    x, mask = rng.normal(size=(5, 3, html_labeller.DIM)), np.ones((5, 3))
    mask[3:, 1] = 0
    y = (rng.random((5, 3)) < 0.5).astype(float)
    _, g = m.gradients(x, mask, y)
    for name in ("xf", "hf", "hb", "cb", "o"):
        k = tuple(rng.integers(0, s) for s in m.w[name].shape)
        old, losses = m.w[name][k], []
        for d in (1e-4, -1e-4):
            m.w[name][k] = old + d
            losses.append(m.gradients(x, mask, y)[0])
        m.w[name][k] = old
        assert g[name][k] == pytest.approx((losses[0] - losses[1]) / 2e-4, rel=0.05, abs=1e-4)


def test_tokenizer_on_broken_markup():
    assert [b.text for b in html_blocks.blocks_of('<p a="x>y">one<p>two<li>three<!-- open')] == ["one", "two", "three"]
    assert html_blocks.blocks_of("<script>never closed <p>x") == []
    assert [b.text for b in html_blocks.blocks_of("1 < 2 and 3 > 2 <")] == ["1 < 2 and 3 > 2 <"]


def test_warc(spark, tmp_path):
    pages = spark.createDataFrame([(1, "http://a/", "<title>T</title><p>Hi <a href='/x'>there</a></p>"), (2, None, None)], "page_id long, url string, html string")
    rows = warc.derivatives(warc.responses_from_pages(pages), "page_id").collect()
    assert Counter(r["record_type"] for r in rows) == {"metadata": 2, "conversion": 2}
    one = {r["record_type"]: r.asDict() for r in rows if r["source_key"] == 1}
    assert one["conversion"]["content"] == "Hi there" and one["metadata"]["refers_to"] == one["conversion"]["refers_to"]
    assert one["conversion"]["block_digest"] == warc.sha1_digest(b"Hi there")
    fields, block = next(warc.records(__import__("io").BytesIO(warc.serialise(one["conversion"]))))
    assert block == b"Hi there" and fields["warc-refers-to"] == one["conversion"]["refers_to"] and fields["warc-payload-digest"] == one["metadata"]["payload_digest"]
    payload = "<p>Füß</p>".encode()
    head = b"HTTP/1.1 200 OK\r\nContent-Type: text/html; charset=utf-8\r\n\r\n"
    raw = b"".join(b"WARC/1.0\r\nWARC-Type: %s\r\nWARC-Record-ID: <urn:uuid:%d>\r\nWARC-Target-URI: http://b/\r\nContent-Length: %d\r\n\r\n%s\r\n\r\n" % (kind, k, len(head + payload), head + payload) for k, kind in enumerate((b"response", b"request", b"response")))
    (tmp_path / "x.warc").write_bytes(raw)
    (tmp_path / "y.warc.gz").write_bytes(__import__("gzip").compress(raw))
    read = warc.read_responses(spark, f"file://{tmp_path}/*.warc*")
    assert read.count() == 4
    texts = {r["content"] for r in warc.derivatives(read).filter("record_type = 'conversion'").collect()}
    assert texts == {"Füß"}
    assert warc.as_warc_members(warc.derivatives(read)).count() == 8


def test_warc_broken_records_and_encodings(spark, tmp_path):
    """Wrong lengths, other record types, chunked and compressed payloads, a file that breaks off."""
    import gzip
    import io
    import zlib

    body = b"<p>Hello <b>there</b></p>"
    chunked = b"%x\r\n%s\r\n%x;x=1\r\n%s\r\n0\r\n\r\n" % (10, body[:10], len(body) - 10, body[10:])
    http = lambda extra, payload: b"HTTP/1.1 200 OK\r\nContent-Type: text/html\r\n" + extra + b"\r\n" + payload
    blocks = [
        http(b"", body), http(b"Transfer-Encoding: chunked\r\n", chunked), http(b"Content-Encoding: gzip\r\n", gzip.compress(body)), http(b"Content-Encoding: deflate\r\n", zlib.compress(body)),
        http(b"Transfer-Encoding: chunked\r\nContent-Encoding: gzip\r\n", body), http(b"Transfer-Encoding: chunked\r\n", b"zz\r\n" + body),
    ]
    lengths = [str(len(b)).encode() for b in blocks]
    lengths[0] = b"many"
    record = lambda k, kind=b"response": b"WARC/1.0\r\nWARC-Type: %s\r\nWARC-Record-ID: <urn:uuid:%d>\r\nContent-Length: %s\r\n\r\n%s\r\n\r\n" % (kind, k, lengths[k], blocks[k])
    raw = b"".join(map(record, range(len(blocks)))) + record(1, b"metadata") + b"WARC/1.0\r\nWARC-Type: response\r\nContent-Length: 99999\r\n\r\nHTTP/1.1 200 OK\r\n\r\n<p>cut"
    assert len(list(warc.records(io.BytesIO(raw)))) == len(blocks) + 2
    (tmp_path / "a.warc").write_bytes(raw)
    (tmp_path / "b.warc.gz").write_bytes(b"".join(gzip.compress(record(k)) for k in range(4))[:-30])
    (tmp_path / "c.warc").write_bytes(b"")
    got = warc.derivatives(warc.read_responses(spark, f"file://{tmp_path}/*.warc*")).filter("record_type = 'conversion'").collect()
    texts = Counter(r["content"] for r in got)
    assert texts["Hello there"] >= 4 + 3 and texts["cut"] == 1 and sum(texts.values()) >= len(blocks) + 4
    assert all(r["source_headers"].startswith("HTTP/1.1 200 OK") for r in got)
    fields, _ = next(warc.records(io.BytesIO(warc.serialise(got[0].asDict()))))
    assert "warc-source-headers" in fields


def test_warc_repeated_and_very_long_pages(spark):
    long = "<p>" + "word " * 200_000 + "</p>"
    pages = spark.createDataFrame([(1, "u", "<p>x</p>"), (1, "u", "<p>x</p>"), (2, "v", long)], "page_id long, url string, html string").withColumn("content", F.lit(1)).withColumn("record_id", F.lit("x"))
    rows = warc.derivatives(warc.responses_from_pages(pages), "page_id").filter("record_type = 'conversion'").collect()
    assert sorted((r["source_key"], r["content_length"]) for r in rows) == [(1, 1), (1, 1), (2, 999_999)]


@pytest.mark.parametrize("name", ["op2_license_scans", "op4_source_mixing", "op5_jaccard_join", "op6_quality_rules", "op7_benchmark_decontamination", "op8_line_dedup", "op10_substring_dedup", "pipeline"])
def test_empty_tables(spark, tmp_path, name):
    import __spark_entry__ as entry

    spark.createDataFrame([], SCHEMA).write.parquet(f"file://{tmp_path}/documents.parquet")
    spark.createDataFrame([], "item_id long, text string").write.parquet(f"file://{tmp_path}/benchmark.parquet")
    assert entry.queries()[name](spark, f"file://{tmp_path}").count() == 0


@pytest.mark.parametrize("name", ["op1_warc_derivatives", "op3_chat_formatting", "op9_html_extraction"])
def test_other_empty_tables(spark, tmp_path, name):
    spark.createDataFrame([], "page_id long, url string, html string").write.parquet(f"file://{tmp_path}/pages.parquet")
    spark.createDataFrame([], chat_format.TURNS).write.parquet(f"file://{tmp_path}/conversations.parquet")
    assert queries.queries()[name](spark, f"file://{tmp_path}").count() == (1 if name.startswith("op3") else 0)


def test_oracles(spark, data_dir):
    import duckdb

    con = duckdb.connect()
    for name in ("documents", "conversations"):
        con.execute(f"create view {name} as select * from read_parquet('{data_dir}/{name}.parquet')")
    for name, sql in queries.oracle_sql().items():
        mine, theirs = queries.queries()[name](spark, data_dir).toPandas(), con.execute(sql).df()
        cols = sorted(mine.columns)
        assert sorted(map(tuple, mine[cols].astype(str).values)) == sorted(map(tuple, theirs[cols].astype(str).values)), name


def test_pipeline_against_brute_force(spark, tmp_path):
    """All five stages on a small table, each checked against a plain version on its own input."""
    import corpus_pipeline as cp

    texts = corpus(3, 40)
    bench = " ".join(f"bench{k}" for k in range(30))
    texts[2] = " ".join(f"u{k}" for k in range(40)) + " " + bench
    texts += [f"shared footer line of words\n{' '.join(f'd{k}x{j}' for j in range(40))}" for k in range(12)]
    spark.createDataFrame([(0, bench)], "item_id long, text string").write.parquet(f"file://{tmp_path}/benchmark.parquet")
    docs = docs_of(spark, texts)
    stage = dict(cp.STAGES)
    a = stage["quality rules"](spark, docs, "")
    kept = {r["doc_id"]: r["text"] for r in a.collect()}
    assert a.columns == docs.columns and 2 in kept and all(len(WORD.findall(t)) >= 20 for t in kept.values())
    b = stage["line dedup"](spark, a, "")
    cut = {r["doc_id"]: r["text"] for r in b.collect()}
    assert b.columns == docs.columns and set(cut) == set(kept) and not any("shared footer" in t for t in cut.values())
    c = stage["n-gram Jaccard join"](spark, b, "")
    assert {r["doc_id"] for r in c.collect()} == {i for i, (_, label) in jaccard_brute(cut).items() if i == label}
    d = stage["benchmark decontamination"](spark, c, f"file://{tmp_path}")
    assert {r["doc_id"] for r in c.collect()} - {r["doc_id"] for r in d.collect()} == {2}
    e = stage["mixing sources to target weights"](spark, d, "")
    assert e.count() == d.count()


def test_decontamination_without_unique_ids(spark):
    rng = random.Random(4)
    words = lambda k: [f"t{rng.randrange(5000)}" for _ in range(k)]
    items = [words(30) for _ in range(3)]
    text = lambda *parts: " ".join(w for p in parts for w in p)
    docs = docs_of(spark, [(None, text(words(9), items[0]), "s"), (None, text(words(40)), "s"), (7, text(items[1], words(9)), "s"), (7, text(words(40)), "s"), (8, text(words(5), items[2]), "s")])
    bench = spark.createDataFrame([(0, text(items[0])), (None, text(items[1])), (None, text(items[2]))], "item_id long, text string")
    assert sorted(((r["doc_id"], r["item_id"]) for r in decontaminate.overlaps(docs, bench).collect()), key=str) == [(7, None), (8, None), (None, 0)]
    assert sorted((r["doc_id"] is None, len(r["text"].split())) for r in decontaminate.drop_contaminated(docs, bench).collect()) == [(False, 40), (True, 40)]


def test_short_items_with_replaced_words(spark):
    rng = random.Random(5)
    words = lambda k: [f"t{rng.randrange(5000)}" for _ in range(k)]
    cases = [(13, (7,)), (14, (7,)), (15, (4, 9)), (17, (4, 9)), (18, (4, 9, 14)), (20, (4, 9, 14))]
    items, docs = [words(n) for n, _ in cases], []
    for item, (_, replaced) in zip(items, cases, strict=True):
        docs.append(" ".join(words(9) + ["other" if k in replaced else w for k, w in enumerate(item)] + words(9)))
    parts = [" ".join(words(9) + item[: len(item) // 2] + words(20)) for item in items]
    bench = spark.createDataFrame([(k, " ".join(w)) for k, w in enumerate(items)], "item_id long, text string")
    found = {(r["doc_id"], r["item_id"]) for r in decontaminate.overlaps(docs_of(spark, docs + parts), bench).collect()}
    assert found == {(k, k) for k in range(len(cases))}


def test_near_duplicates_without_unique_ids(spark):
    import corpus_pipeline as cp

    a, b, c = (" ".join(f"{x}{k}" for k in range(60)) for x in "abc")
    near = lambda t: t.rsplit(" ", 1)[0] + " end"
    rows = [(None, a, "s"), (None, a, "s"), (None, near(a), "s"), (5, b, "s"), (5, near(b), "s"), (5, c, "s"), (3, near(c), "s"), (None, c, "s"), (None, None, "s"), (9, "", "s"), (9, "", "s")]
    out = cp.near_duplicates(spark, docs_of(spark, rows), "")
    got = [(r["doc_id"], r["text"]) for r in out.collect()]
    assert len(got) == 5 and sum(i is None and t in (a, near(a)) for i, t in got) == 1
    assert sum(t in (b, near(b)) for _, t in got) == 1 and {(3, near(c)), (None, None), (9, "")} <= set(got)
