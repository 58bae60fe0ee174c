"""Substring dedup by recompression.

Each text is a string of words. A round names maximal runs of one symbol, then pairs: every symbol's name
gives it a side, and each left symbol joins a right symbol that follows it. Names are hashes of what
they stand for, hence global: equal substrings get equal interior symbols in all tasks, whoever names them.

The lowest levels (``ROUNDS`` = 2 rounds, symbols of up to ``MAX_SPAN`` words, runs in the first) need nothing but the text itself and are
made where the text lies. With runs named in the first round only and spans up to 2, then 4 words, at most 2 + 1 + 3 words are
lost at each end, so that two equal windows of 50 words share an interior of 38 words or more: 10 whole symbols at
least, which hold 7 groups of 4 symbols in a row. Such a group is a symbol of the third level; of each ``NEIGHBOURS`` = 7 of them in a row
the one with the smallest name is an *anchor*: equal windows always share one, with all its words. From there on a level is a Spark round:

1. *Groups.* Anchors are brought together by name. One that stands in a single text is no part of a repeat and goes no further.
2. *Windows.* Around what is left, the runs of 50 words are named and brought together; each one that a text with a smaller id has
   too gets that text's place as its witness.
3. *Passages.* Neighbouring windows whose witnesses are neighbours are one symbol, a maximal repeat. Its words are compared with those at its
   witness, by a 128-bit digest of the words themselves, once for each passage and not for each of its places. A passage whose
   words differ (a collision of names below) is not removed.

The name of a whole text, the top of the hierarchy, settles exact copies without looking inside; it is a 128-bit digest of the words too.

Both exchanges of names settle what they can within a task's texts first, so that a passage in a third of all texts is
sent once per task and not once per text; what arrives is sorted by Spark and streamed, so no task holds a partition.

Defined cases: null or empty text: no words, nothing removed, empty kept text; repeated rows (same id):
a smaller id is asked for, so they don't remove each other; null ids sort before all others; an empty table
gives an empty result; other columns aren't read, whatever their names. Two different passages of one 64-bit name (a chance of
about n * n / 2**65 for n windows that were named) stay unless one has another witness.
"""

from __future__ import annotations

import hashlib
from collections.abc import Iterator

import numpy as np
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from coordloom.llm.common import materialise

WINDOW = 50
ROUNDS = 2
MAX_SPAN = 4
GROUP = 4
NEIGHBOURS = 7


def parse(names: np.ndarray, ends: np.ndarray, rounds: int = ROUNDS, max_span: int = MAX_SPAN) -> tuple[np.ndarray, np.ndarray, np.ndarray]:
    """Symbols of a flat array of words after some rounds: (name, first word, words).

    ``ends`` marks the last word of each text; nothing is joined across it. Runs: equal neighbours
    are named by a run step first; pairs: a symbol whose name has bit 40 unset joins the next one if that has it
    set. Equal neighbours never pair, so the run step decides for them alone.
    """
    from coordloom.llm.hashing import MULTIPLIERS, U, mix

    names, start, span, last = names.copy(), np.arange(len(names)), np.ones(len(names), np.int64), ends.copy()
    for r in range(rounds):
        # runs, in the first round: only those that end within max_span words become one symbol; longer ones stay as they are
        if r == 0 and len(names) > 1:
            head = np.ones(len(names), dtype=bool)
            head[1:] = (names[1:] != names[:-1]) | last[:-1]
            first = np.flatnonzero(head)
            count = np.diff(np.append(first, len(names)))
            total = count * span[first]
            fits = total <= min(max_span, 2 << r)
            group = np.repeat(np.arange(len(first)), count)
            keep = head | ~fits[group]
            merged = fits & (count > 1)
            new = names.copy()
            new[first[merged]] = mix(names[first[merged]] * MULTIPLIERS[10] + count[merged].astype(np.uint64) * MULTIPLIERS[11])
            wide = span.copy()
            wide[first[merged]] = total[merged]
            ending = last.copy()
            ending[first[merged]] = last[first[merged] + count[merged] - 1]
            names, start, span, last = new[keep], start[keep], wide[keep], ending[keep]
        if len(names) < 2:
            break
        side = ((names >> U(40)) & U(1)).astype(bool)
        pair = np.zeros(len(names), dtype=bool)
        pair[:-1] = ~side[:-1] & side[1:] & ~last[:-1] & (span[:-1] + span[1:] <= min(max_span, 2 << r))
        taken = np.append(False, pair[:-1])
        at = np.flatnonzero(pair)
        new, wide, ending = names.copy(), span.copy(), last.copy()
        new[at] = mix(names[at] * MULTIPLIERS[12] + names[at + 1] * MULTIPLIERS[13])
        wide[at] += span[at + 1]
        ending[at] = last[at + 1]
        names, start, span, last = new[~taken], start[~taken], wide[~taken], ending[~taken]
    return names, start, span


def anchors(names: np.ndarray, start: np.ndarray, span: np.ndarray, owner: np.ndarray) -> tuple[np.ndarray, np.ndarray, np.ndarray, np.ndarray]:
    """(name, owner, first word, words) of the groups that are the smallest of some NEIGHBOURS in a row within one text (ties: all)."""
    from coordloom.llm.hashing import spans_of

    group = spans_of(names, GROUP)
    n = len(group) - NEIGHBOURS + 1
    chosen = np.zeros(len(group), dtype=bool)
    if n > 0:
        low = group[:n].copy()
        for k in range(1, NEIGHBOURS):
            np.minimum(low, group[k : k + n], out=low)
        inside = owner[:n] == owner[NEIGHBOURS + GROUP - 2 :]
        for k in range(NEIGHBOURS):
            chosen[k : k + n] |= inside & (group[k : k + n] == low)
    at = np.flatnonzero(chosen)
    last = at + GROUP - 1
    return group[at], owner[at], start[at], start[last] + span[last] - start[at]


NULL_ID = -(1 << 62)
#: Names that a task remembers to have sent; more than that and the oldest are forgotten.
MEMORY = 1 << 18


def _slices(batches: Iterator):
    """(part, ids, words, bounds, marks of last words) for each slice of texts."""
    import pyarrow as pa

    from coordloom.llm import hashing

    for batch in batches:
        for part in hashing.slices(batch):
            words, bounds = hashing.word_hashes(part.column(1), lower=False)
            ends = np.zeros(len(words), dtype=bool)
            ends[bounds[1:][np.diff(bounds) > 0] - 1] = True
            yield part, np.asarray(part.column(0).cast(pa.int64()).fill_null(NULL_ID)), words, bounds, ends


def _digest(words: list[bytes]) -> bytes:
    return hashlib.blake2b(b" ".join(words), digest_size=16).digest()


def _top(words: list[bytes]) -> tuple[int, int]:
    digest = _digest(words)
    return int.from_bytes(digest[:8], "big", signed=True), int.from_bytes(digest[8:], "big", signed=True)


def _tag(words: list[bytes]) -> int:
    """31 bits of a text's name: tells rows with the same id apart."""
    return _top(words)[0] & 0x7FFFFFFF


def _texts(column) -> Iterator[bytes]:
    import pyarrow as pa

    for text in column.cast(pa.large_binary()):
        yield text.as_py() or b""


PACK_BYTES = 1 << 20


def packed_texts(docs: DataFrame) -> DataFrame:
    """(id, z): texts as zstd frames, for the exchanges by id."""

    def run(batches: Iterator) -> Iterator:
        import pyarrow as pa
        import zstandard

        press = zstandard.ZstdCompressor(level=1)
        for batch in batches:
            frames = pa.array([press.compress(t) if t else None for t in _texts(batch.column(1))], pa.binary())
            yield pa.RecordBatch.from_arrays([batch.column(0).cast(pa.int64()).fill_null(NULL_ID), frames], names=["id", "z"])

    return docs.mapInArrow(run, "id long, z binary")


def unpacked(batches: Iterator) -> Iterator:
    """Parts of the batches with the first column's frames as texts, about PACK_BYTES of frames at a time."""
    import pyarrow as pa
    import zstandard

    from coordloom.llm import hashing

    press = zstandard.ZstdDecompressor()
    for batch in batches:
        for part in hashing.slices(batch, 0, PACK_BYTES):
            texts = pa.array([press.decompress(z) if z else b"" for z in part.column(0).to_pylist()], pa.large_binary())
            yield pa.RecordBatch.from_arrays([texts, *part.columns[1:]], names=part.schema.names)


def text_names(docs: DataFrame) -> DataFrame:
    """(id, n, t1, t2): the number of words and the name of the whole text, the last symbol of its recompression."""

    def run(batches: Iterator) -> Iterator:
        import pyarrow as pa

        from coordloom.llm import hashing

        for batch in batches:
            for part in hashing.slices(batch):
                rows = [(len(w), *_top(w)) for w in (t.split() for t in _texts(part.column(1)))]
                yield pa.RecordBatch.from_arrays([part.column(0).cast(pa.int64()).fill_null(NULL_ID), *(pa.array([r[k] for r in rows], pa.int64()) for k in range(3))], names=["id", "n", "t1", "t2"])

    return docs.mapInArrow(run, "id long, n long, t1 long, t2 long")


def _heads(*keys: np.ndarray) -> np.ndarray:
    """True where a sorted run of equal keys begins."""
    head = np.ones(len(keys[0]), dtype=bool)
    if len(head):
        head[1:] = np.logical_or.reduce([k[1:] != k[:-1] for k in keys])
    return head


#: A hit is a long: first word of the anchor times 64 plus its number of words.
SPAN_BITS = 64


def anchor_hits(docs: DataFrame, window: int = WINDOW) -> DataFrame:
    """The first Spark round: (id, hit) of the anchors that stand in two texts or more."""

    def emit(batches: Iterator) -> Iterator:
        import pyarrow as pa

        told = np.empty(0, np.int64)  # names that this task knows to be shared and has told so
        for _, ids, words, bounds, ends in _slices(batches):
            symbols, start, span = parse(words, ends)
            name, who, first_word, length = anchors(symbols, start, span, np.searchsorted(bounds, start, side="right") - 1)
            enough = (np.diff(bounds) >= window)[who]
            order = np.argsort(name[enough], kind="stable")
            if not len(order):
                continue
            name, who = name[enough][order].view(np.int64), who[enough][order]
            hit = ((first_word[enough][order] - bounds[who]) * SPAN_BITS + length[enough][order]).astype(np.int64)
            head = _heads(name)
            first = np.flatnonzero(head)
            last = np.append(first[1:], len(name)) - 1
            many = (who[first] != who[last])[np.cumsum(head) - 1]
            known = np.isin(name, told)
            # met in two texts of this task: settled, and one row tells the others; all else goes on as it is
            signal = np.flatnonzero(many & head & ~known)
            settled = many | known
            yield pa.RecordBatch.from_arrays([pa.array(name, mask=settled), pa.array(ids[who]), pa.array(hit)], names=["name", "id", "hit"])
            yield pa.RecordBatch.from_arrays([pa.array(name[signal]), pa.nulls(len(signal), pa.int64()), pa.nulls(len(signal), pa.int64())], names=["name", "id", "hit"])
            told = np.concatenate((name[signal], told))[:MEMORY]

    def settle(batches: Iterator) -> Iterator:
        """Rows come sorted by name and id, those of settled names first. Of a name at most one text's rows are held back."""
        import pyarrow as pa

        def out(owner: np.ndarray, hit: np.ndarray):
            return pa.RecordBatch.from_arrays([pa.array(owner), pa.array(hit)], names=["id", "hit"])

        held = [np.empty(0, np.int64)] * 3
        for batch in batches:
            done = np.asarray(batch.column(0).is_null())
            if done.any():
                part = batch.filter(pa.array(done))
                yield out(part.column(1), part.column(2))
                batch = batch.filter(pa.array(~done))
            if not batch.num_rows:
                continue
            fresh = (np.asarray(batch.column(0)), np.asarray(batch.column(1).fill_null(NULL_ID - 1)), np.asarray(batch.column(2).fill_null(0)))
            name, owner, hit = (np.concatenate(c) for c in zip(held, fresh, strict=True))
            head = _heads(name)
            first = np.flatnonzero(head)
            last = np.append(first[1:], len(name)) - 1
            several = owner[first] != owner[last]
            met = several[np.cumsum(head) - 1] & (owner != NULL_ID - 1)
            if met.any():
                yield out(owner[met], hit[met])
            # the last name may go on: one row that marks it as shared, or its rows so far
            held = [name[-1:], np.array([NULL_ID - 1]), np.zeros(1, np.int64)] if several[-1] else [c[first[-1] :] for c in (name, owner, hit)]

    rows = docs.mapInArrow(emit, "name long, id long, hit long")
    return rows.repartition(F.coalesce("name", "id")).sortWithinPartitions("name", "id").mapInArrow(settle, "id long, hit long")


def _starts_near(hits: np.ndarray, n: int, window: int) -> np.ndarray:
    """Starts of the windows of a text of ``n`` words that hold a whole hit."""
    first, length = hits // SPAN_BITS, hits % SPAN_BITS
    fits = first + length <= n
    first, length = first[fits], length[fits]
    marks = np.zeros(n + 2, dtype=np.int64)
    np.add.at(marks, np.maximum(0, first + length - window), 1)
    np.add.at(marks, first + 1, -1)
    return np.flatnonzero(np.cumsum(marks[: max(0, n - window + 1)]) > 0)


WITNESSED = "id long, tag int, start int, w_id long, w_tag int, w_start int"


def repeated_windows(texts: DataFrame, window: int = WINDOW) -> DataFrame:
    """The second Spark round: windows near hits that a text with a smaller id has too, with that text and place. ``texts``: (z, id, hits, copies)."""
    names = [c.split()[0] for c in WITNESSED.split(", ")]

    def emit(batches: Iterator) -> Iterator:
        import pyarrow as pa

        from coordloom.llm import hashing

        memory = [np.empty(0, np.int64), np.empty(0, np.int64), np.empty(0, np.int32), np.empty(0, np.int32)]  # name, smallest id sent, tag, start; sorted
        for batch in unpacked(batches):
            for part in hashing.slices(batch, 0):
                words, bounds = hashing.word_hashes(part.column(0), lower=False)
                ids, tags, spans = np.asarray(part.column(1)), np.zeros(part.num_rows, dtype=np.int32), hashing.spans_of(words, window)
                starts, who = [], []
                for k, (text, hits, copies) in enumerate(zip(_texts(part.column(0)), part.column(2), part.column(3), strict=True)):
                    lo, n = bounds[k], bounds[k + 1] - bounds[k]
                    tags[k] = _tag(text.split())
                    if tags[k] in (copies.as_py() or ()):
                        continue  # an exact copy of a text with a smaller id has nothing that one doesn't
                    near = _starts_near(np.asarray(hits.values.to_numpy(), dtype=np.int64), n, window)
                    starts.append(near + lo)
                    who.append(np.full(len(near), k))
                at = np.concatenate(starts) if starts else np.empty(0, np.int64)
                if not len(at):
                    continue
                who = np.concatenate(who)
                name, owner, place = spans[at].view(np.int64), ids[who], (at - bounds[who]).astype(np.int32)
                order = np.lexsort((place, owner, name))
                name, owner, place, tag = name[order], owner[order], place[order], tags[who][order]
                head = _heads(name)
                first = np.flatnonzero(head)
                group = np.cumsum(head) - 1
                w_owner, w_tag, w_place = owner[first][group], tag[first][group], place[first][group]
                at = np.minimum(np.searchsorted(memory[0], name), max(0, len(memory[0]) - 1))
                if len(memory[0]):  # this task has sent the name with a smaller id
                    known = (memory[0][at] == name) & (memory[1][at] < w_owner)
                    w_owner, w_tag, w_place = (np.where(known, m[at], w) for m, w in zip(memory[1:], (w_owner, w_tag, w_place), strict=True))
                met = owner > w_owner
                witness = [pa.array(c, t, mask=~met) for c, t in ((w_owner, pa.int64()), (w_tag, pa.int32()), (w_place, pa.int32()))]
                yield pa.RecordBatch.from_arrays([pa.array(name, mask=met), pa.array(owner), pa.array(tag), pa.array(place), *witness], names=["name", *names])
                several = np.flatnonzero(np.bincount(group[met], minlength=len(first)) > 0)  # names met in two texts: likely to come again
                pick = first[several]
                pool = [np.concatenate((a, b)) for a, b in zip((name[pick], w_owner[pick], w_tag[pick], w_place[pick]), memory, strict=True)]
                order = np.lexsort((pool[1], pool[0]))
                pool = [c[order] for c in pool]
                keep = _heads(pool[0])
                memory = [c[keep] for c in pool] if keep.sum() <= MEMORY else [c[np.argsort(name[pick], kind="stable")] for c in (name[pick], w_owner[pick], w_tag[pick], w_place[pick])]

    def settle(batches: Iterator) -> Iterator:
        """Rows come sorted by name, id and start, settled ones first; of a name only its first row is held."""
        import pyarrow as pa

        held = None
        for batch in batches:
            done = np.asarray(batch.column(0).is_null())
            if done.any():
                part = batch.filter(pa.array(done))
                yield pa.RecordBatch.from_arrays(part.columns[1:], names=names)
                batch = batch.filter(pa.array(~done))
            if not batch.num_rows:
                continue
            name, owner, tag, place = (np.asarray(c) for c in batch.columns[:4])
            if held is not None:
                name, owner, tag, place = (np.concatenate((h, c)) for h, c in zip(held, (name, owner, tag, place), strict=True))
            head = _heads(name)
            first = np.flatnonzero(head)
            group = np.cumsum(head) - 1
            met = owner > owner[first][group]
            if met.any():
                w = first[group[met]]
                yield pa.RecordBatch.from_arrays([pa.array(c) for c in (owner[met], tag[met], place[met], owner[w], tag[w], place[w])], names=names)
            held = [c[first[-1] : first[-1] + 1] for c in (name, owner, tag, place)]

    rows = texts.mapInArrow(emit, f"name long, {WITNESSED}")
    return rows.repartition(F.coalesce("name", "id")).sortWithinPartitions("name", "id", "start").mapInArrow(settle, WITNESSED)


def _passages(starts: list[dict], tag: int) -> list[tuple[int, int, int, int, int]]:
    """(start, windows, w_id, w_tag, w_start): windows in a row whose witnesses are in a row, as one symbol."""
    out: list[list[int]] = []
    for s in sorted((s for s in starts if s["tag"] == tag), key=lambda s: s["start"]):
        if out and s["start"] == out[-1][0] + out[-1][1] and (s["w_id"], s["w_tag"], s["w_start"]) == (out[-1][2], out[-1][3], out[-1][4] + out[-1][1]):
            out[-1][1] += 1
        elif not (out and s["start"] < out[-1][0] + out[-1][1]):
            out.append([s["start"], 1, s["w_id"], s["w_tag"], s["w_start"]])
    return [tuple(p) for p in out]


CLAIM = "w_id long, w_tag int, w_start int, size int, words binary"


def _claims(texts: DataFrame, window: int) -> DataFrame:
    """(w_id, w_tag, w_start, size, words): what each passage says its witness holds, as a digest of its words; once for each different claim."""

    def run(batches: Iterator) -> Iterator:
        import pyarrow as pa

        for batch in unpacked(batches):
            rows = set()
            for text, starts in zip(_texts(batch.column(0)), batch.column(1), strict=True):
                words = text.split()
                rows |= {(w, t, at, n, _digest(words[lo : lo + n + window - 1])) for lo, n, w, t, at in _passages(starts.as_py(), _tag(words))}
            rows = sorted(rows)
            kinds = (pa.int64(), pa.int32(), pa.int32(), pa.int32(), pa.binary())
            yield pa.RecordBatch.from_arrays([pa.array([r[k] for r in rows], t) for k, t in enumerate(kinds)], names=[c.split()[0] for c in CLAIM.split(", ")])

    return texts.select("z", "starts").mapInArrow(run, CLAIM).distinct()


def _refuted(claims: DataFrame, texts: DataFrame, window: int) -> DataFrame:
    """The claims that the witness's words don't bear out. ``texts``: (id, z)."""

    def run(batches: Iterator) -> Iterator:
        import pyarrow as pa

        for batch in unpacked(batches):
            bad = []
            for text, claims in zip(_texts(batch.column(0)), batch.column(1), strict=True):
                words = text.split()
                tag = _tag(words)
                bad += [c for c in claims.as_py() if c["w_tag"] == tag and _digest(words[c["w_start"] : c["w_start"] + c["size"] + window - 1]) != c["words"]]
            columns = [c.split()[0] for c in CLAIM.split(", ")]
            kinds = (pa.int64(), pa.int32(), pa.int32(), pa.int32(), pa.binary())
            yield pa.RecordBatch.from_arrays([pa.array([c[k] for c in bad], t) for k, t in zip(columns, kinds, strict=True)], names=columns)

    by_text = claims.groupBy("w_id").agg(F.collect_list(F.struct("w_id", "w_tag", "w_start", "size", "words")).alias("claims"))
    asked = texts.join(by_text.hint("merge"), texts["id"] == by_text["w_id"]).select("z", "claims")
    return asked.mapInArrow(run, CLAIM)


RESULT = "doc_id long, n_words long, n_removed long, kept string"


def _kept(rows: DataFrame, window: int, refuted: set[tuple]) -> DataFrame:
    """From (z, id, copies, starts): the words outside the passages that were borne out; none of an exact copy."""

    def run(batches: Iterator) -> Iterator:
        import pyarrow as pa

        def one(text: bytes, copies: list | None, starts: list | None) -> tuple[int, int, str]:
            words = text.split()
            n = len(words)
            tag = _tag(words) if copies or starts else 0
            if n >= window and tag in (copies or ()):
                return n, n, ""
            marks = np.zeros(n + 1, dtype=np.int64)
            for lo, size, w, t, at in _passages(starts or [], tag):
                if lo + size + window - 1 <= n and not (refuted and (w, t, at, size, _digest(words[lo : lo + size + window - 1])) in refuted):
                    marks[lo] += 1
                    marks[lo + size + window - 1] -= 1
            if not marks.any():
                return n, 0, b" ".join(words).decode()
            gone = (np.cumsum(marks[:-1]) > 0).tolist()
            return n, sum(gone), b" ".join(w for w, g in zip(words, gone, strict=True) if not g).decode()

        for part in unpacked(batches):
            out = [one(t, c.as_py(), s.as_py()) for t, c, s in zip(_texts(part.column(0)), part.column(2), part.column(3), strict=True)]
            ids = pa.array([None if i == NULL_ID else i for i in part.column(1).to_pylist()], pa.int64())
            yield pa.RecordBatch.from_arrays([ids, *(pa.array([o[k] for o in out], t) for k, t in enumerate((pa.int64(), pa.int64(), pa.string())))], names=["doc_id", "n_words", "n_removed", "kept"])

    return rows.mapInArrow(run, RESULT)


#: Refuted claims that the driver may carry; so many collisions mean that the names are broken.
MAX_REFUTED = 100_000


def remove_repeats(docs: DataFrame, doc_id: str = "doc_id", text: str = "text", window: int = WINDOW) -> DataFrame:
    """(doc_id, n_words, n_removed, kept) per row."""
    if window < WINDOW:
        raise ValueError("the anchors are proven for windows of 50 words or more")
    rows = docs.select(F.col(f"`{doc_id}`").cast("long").alias("doc_id"), F.col(f"`{text}`").alias("text"))
    names = materialise(text_names(rows), "text-names")
    firsts = names.filter(F.col("n") >= window).groupBy("t1", "t2").agg(F.min("id").alias("first"), F.max("id").alias("last")).filter("first < last").select("t1", "t2", "first")
    copies = names.join(firsts, ["t1", "t2"]).filter("id > first").groupBy("id").agg(F.collect_set(F.col("t1").bitwiseAND(0x7FFFFFFF).cast("int")).alias("copies"))
    hits = anchor_hits(rows, window).groupBy("id").agg(F.collect_set("hit").alias("hits"))
    notes = materialise(hits.join(copies, "id", "full"), "notes")
    keyed = packed_texts(rows)
    noted = keyed.join(notes.filter("hits is not null").hint("merge"), "id").select("z", "id", "hits", "copies")
    found = repeated_windows(noted, window)
    starts = materialise(found.groupBy("id").agg(F.collect_list(F.struct("tag", "start", "w_id", "w_tag", "w_start")).alias("starts")), "windows")
    claims = _claims(keyed.join(starts.hint("merge"), "id").select("z", "starts"), window)
    bad = _refuted(claims, keyed, window).limit(MAX_REFUTED + 1).collect()
    if len(bad) > MAX_REFUTED:
        raise ValueError("too many names stand for different words")
    refuted = {(r["w_id"], r["w_tag"], r["w_start"], r["size"], bytes(r["words"])) for r in bad}
    found = notes.select("id", "copies").filter("copies is not null").join(starts, "id", "full")
    final = keyed.join(found.hint("merge"), "id", "left").select("z", "id", "copies", "starts")
    return _kept(final, window, refuted)
