"""Chat formatting: schema fingerprints select declarative mappings to canonical turns, a template renders them.

A record's fingerprint is the SHA-256 of its sorted nested field paths (lists as ``[]``; fields that
are null don't count). Each mapping declares the paths it needs and may have, so its fingerprints
are known beforehand and a record finds its mapping by one lookup; a table whose rows all have one
schema finds it once, on the driver.

The template marks turns with control strings. A control string inside a text gets a word joiner
(U+2060) after its first character, one more than it has already, and reading takes one away:
texts without such strings stay as they are, and every text comes back exactly.

Defined cases: null text or role: empty string; ties in ``turn`` are ordered by role, then text; a
conversation without rows doesn't exist; a null conv_id is one conversation; records with an unknown
fingerprint or broken JSON give one row in ``unmapped`` and no turns (a row with a negative turn is never formatted); ids keep all
their 64 bits beside null ones; extra columns of a turn table don't change its layout, whatever their names.
"""

from __future__ import annotations

import hashlib
import itertools
import json
import re
from collections.abc import Iterator
from dataclasses import dataclass

from pyspark.sql import DataFrame
from pyspark.sql import functions as F
from pyspark.sql import types as T

JOINER = "⁠"
#: The template's control strings.
SYS, SYS_END, USER, USER_END, ANSWER_END, OTHER, OTHER_TEXT, OTHER_END, START = "<<SYS>>", "<</SYS>>", "[INST]", "[/INST]", "</s>", "[ROLE]", "[:]", "[/ROLE]", "<s>"
CONTROLS = (SYS, SYS_END, USER, USER_END, ANSWER_END, OTHER, OTHER_TEXT, OTHER_END, START)
_INSIDE = re.compile("|".join(re.escape(c[0]) + JOINER + "*" + re.escape(c[1:]) for c in CONTROLS))
_CONTROL = re.compile("|".join(map(re.escape, sorted(CONTROLS, key=len, reverse=True))))


def escape(text: str) -> str:
    return _INSIDE.sub(lambda m: m[0][0] + JOINER + m[0][1:], text)


def unescape(text: str) -> str:
    return _INSIDE.sub(lambda m: m[0][0] + m[0][2:] if m[0][1] == JOINER else m[0], text)


def render(turns: list[tuple[str, str]]) -> tuple[str, list[tuple[int, int]]]:
    """The formatted text and the (start, stop) of each assistant text: the loss mask."""
    parts, at, mask = [START], len(START), []
    for role, text in turns:
        body = escape(text)
        if role == "system":
            piece = SYS + body + SYS_END
        elif role == "user":
            piece = USER + body + USER_END
        elif role == "assistant":
            piece = body + ANSWER_END
            mask.append((at, at + len(body)))
        else:
            piece = OTHER + escape(role) + OTHER_TEXT + body + OTHER_END
        parts.append(piece)
        at += len(piece)
    return "".join(parts), mask


_ROLE_OF = {SYS_END: "system", USER_END: "user", ANSWER_END: "assistant"}


def read_back(formatted: str) -> list[tuple[str, str]]:
    """The turns of a formatted text."""
    turns, last, role = [], len(START), None
    for m in _CONTROL.finditer(formatted, last):
        token = m[0]
        if token == OTHER_TEXT:
            role = unescape(formatted[last : m.start()])
        elif token == OTHER_END:
            turns.append((role, unescape(formatted[last : m.start()])))
        elif token in _ROLE_OF:
            turns.append((_ROLE_OF[token], unescape(formatted[last : m.start()])))
        last = m.end()
    return turns


# Layouts


@dataclass(frozen=True)
class Mapping:
    """``steps``: (role, path) for one field, or (list path, role field, text field) for each item of a list."""

    name: str
    needs: tuple[str, ...]
    steps: tuple[tuple[str, ...], ...]
    may: tuple[str, ...] = ()

    def fingerprints(self) -> Iterator[str]:
        for n in range(len(self.may) + 1):
            for extra in itertools.combinations(self.may, n):
                yield fingerprint_of({*self.needs, *extra})


ROLE_NAMES = {"human": "user", "prompter": "user", "user": "user", "gpt": "assistant", "bot": "assistant", "model": "assistant", "assistant": "assistant", "system": "system"}
_IDS = ("id", "source")
MAPPINGS: tuple[Mapping, ...] = (
    Mapping("turn-rows", ("conv_id", "turn", "role", "text"), (("row", "role", "text"),)),
    Mapping("prompt-response", ("prompt", "response"), (("system", "system"), ("user", "prompt"), ("assistant", "response")), ("system", *_IDS)),
    Mapping("prompt-completion", ("prompt", "completion"), (("system", "system"), ("user", "prompt"), ("assistant", "completion")), ("system", *_IDS)),
    Mapping("question-answer", ("question", "answer"), (("user", "context+question"), ("assistant", "answer")), ("context", *_IDS)),
    Mapping("instruction", ("instruction", "output"), (("system", "system"), ("user", "instruction+input"), ("assistant", "output")), ("input", "system", *_IDS)),
    Mapping("messages", ("messages[].role", "messages[].content"), (("messages", "role", "content"),), _IDS),
    Mapping("messages-parts", ("messages[].role", "messages[].content[].type", "messages[].content[].text"), (("messages", "role", "content"),), _IDS),
    Mapping("conversations", ("conversations[].from", "conversations[].value"), (("system", "system"), ("conversations", "from", "value")), ("system", *_IDS)),
    Mapping("dialog", ("dialog[].speaker", "dialog[].text"), (("dialog", "speaker", "text"),), _IDS),
    Mapping("nested-chat", ("chat.messages[].author.role", "chat.messages[].text"), (("chat.messages", "author.role", "text"),), _IDS),
    Mapping("preference", ("prompt", "chosen", "rejected"), (("user", "prompt"), ("assistant", "chosen")), _IDS),
)


def paths_of(value, at: str = "") -> set[str]:
    if isinstance(value, dict):
        return set().union(*(paths_of(v, f"{at}.{k}" if at else k) for k, v in value.items())) if value else set()
    if isinstance(value, list):
        return set().union(*(paths_of(v, f"{at}[]") for v in value)) if value else {f"{at}[]"}
    return set() if value is None else {at}


def paths_of_schema(kind: T.DataType, at: str = "") -> set[str]:
    if isinstance(kind, T.StructType):
        return set().union(*(paths_of_schema(f.dataType, f"{at}.{f.name}" if at else f.name) for f in kind.fields))
    if isinstance(kind, T.ArrayType):
        return paths_of_schema(kind.elementType, f"{at}[]")
    return {at}


def fingerprint_of(paths: set[str]) -> str:
    return hashlib.sha256("\n".join(sorted(paths)).encode()).hexdigest()


REGISTRY = {print_: m for m in reversed(MAPPINGS) for print_ in m.fingerprints()}


def _at(value, path: str):
    for key in path.split("."):
        value = value.get(key) if isinstance(value, dict) else None
    return value


def _text(value) -> str:
    if isinstance(value, list):
        return "".join(_text(v) for v in value)
    if isinstance(value, dict):
        return _text(value.get("text"))
    return "" if value is None else value if isinstance(value, str) else json.dumps(value, ensure_ascii=False)


def turns_of_record(record) -> tuple[str, str | None, list[tuple[str, str]]]:
    """(fingerprint, name of the mapping or None, canonical turns)."""
    key = fingerprint_of(paths_of(record))
    mapping = REGISTRY.get(key)
    if mapping is None:
        return key, None, []
    turns = []
    for step in mapping.steps:
        if step[0] == "row":
            turns.append((_text(_at(record, step[1])), _text(_at(record, step[2]))))
        elif len(step) == 3:
            for item in _at(record, step[0]) or []:
                role = _text(_at(item, step[1]))
                turns.append((ROLE_NAMES.get(role.lower(), role), _text(_at(item, step[2]))))
        else:
            values = [v for v in (_at(record, p) for p in step[1].split("+")) if v is not None]
            if values:
                turns.append((step[0], "\n\n".join(map(_text, values))))
    return key, mapping.name, turns


TURNS = "conv_id long, turn long, role string, text string"


MAPPED = TURNS + ", layout string, fingerprint string"


def mapped_records(records: DataFrame, conv_id: str = "conv_id", record: str = "record") -> DataFrame:
    """Heterogeneous JSON records to (conv_id, turn, role, text, layout, fingerprint); a record of unknown layout gives one row with turn -1 and layout null."""

    def convert(batches: Iterator) -> Iterator:
        import pyarrow as pa

        kinds = (pa.int64(), pa.int64(), *[pa.string()] * 4)
        for batch in batches:
            rows = []
            for cid, raw in zip(batch.column(0).to_pylist(), batch.column(1).to_pylist(), strict=True):
                try:
                    key, name, turns = turns_of_record(json.loads(raw))
                except (TypeError, ValueError, RecursionError):
                    key, name, turns = "", None, []
                rows += [(cid, k, *t, name, key) for k, t in enumerate(turns)] if name else [(cid, -1, "", "", None, key)]
            yield pa.RecordBatch.from_arrays([pa.array([r[k] for r in rows], t) for k, t in enumerate(kinds)], names=[c.split()[0] for c in MAPPED.split(", ")])

    source = records.select(F.col(f"`{conv_id}`").cast("long").alias("conv_id"), F.col(f"`{record}`").alias("record"))
    return source.mapInArrow(convert, MAPPED)


def turns_from_json(records: DataFrame, conv_id: str = "conv_id", record: str = "record") -> DataFrame:
    """The canonical turns of the records whose layout is known."""
    return mapped_records(records, conv_id, record).filter("layout is not null")


def unmapped(records: DataFrame, conv_id: str = "conv_id", record: str = "record") -> DataFrame:
    """(conv_id, fingerprint) of the records whose layout isn't known; an empty fingerprint is broken JSON."""
    return mapped_records(records, conv_id, record).filter("layout is null").select("conv_id", "fingerprint")


def turns_from_table(table: DataFrame, columns: tuple[str, ...] = ("conv_id", "turn", "role", "text")) -> DataFrame:
    """A table with one schema: its fingerprint selects the mapping once; needs no Python on the rows."""
    rows = table.select(*[F.col(f"`{c}`") for c in columns])
    mapping = REGISTRY.get(fingerprint_of(paths_of_schema(rows.schema)))
    if mapping is None or mapping.steps[0][0] != "row":
        raise ValueError(f"no row mapping for the paths {sorted(paths_of_schema(rows.schema))}")
    _, role, text = mapping.steps[0]
    return rows.select(F.col("conv_id").cast("long").alias("conv_id"), F.col("turn").cast("long").alias("turn"), F.coalesce(role, F.lit("")).alias("role"), F.coalesce(text, F.lit("")).alias("text"))


FORMATTED = "conv_id long, formatted string, loss_mask array<struct<start:int,stop:int>>"


def format_turns(turns: DataFrame) -> DataFrame:
    """(conv_id, formatted, loss_mask). A conversation is one row of the result, so its turns meet in one row."""
    grouped = turns.filter("turn is null or turn >= 0").select("conv_id", "turn", F.coalesce("role", F.lit("")).alias("role"), F.coalesce("text", F.lit("")).alias("text")).groupBy("conv_id").agg(F.collect_list(F.struct("turn", "role", "text")).alias("turns"))

    def convert(batches: Iterator) -> Iterator:
        import pyarrow as pa

        kind = pa.list_(pa.struct([("start", pa.int32()), ("stop", pa.int32())]))
        for batch in batches:
            for lo in range(0, batch.num_rows, 256):  # a part at a time: conversations can be long
                part, texts, masks = batch.slice(lo, 256), [], []
                for group in part.column(1):
                    rows = sorted(group.as_py(), key=lambda t: (t["turn"] is not None, t["turn"] or 0, t["role"], t["text"]))
                    text, mask = render([(t["role"], t["text"]) for t in rows])
                    texts.append(text)
                    masks.append([{"start": a, "stop": b} for a, b in mask])
                yield pa.RecordBatch.from_arrays([part.column(0), pa.array(texts, pa.string()), pa.array(masks, kind)], names=["conv_id", "formatted", "loss_mask"])

    return grouped.mapInArrow(convert, FORMATTED)


DIGEST = "conv_id long, n_turns long, turns_sha256 string, loss_chars long, loss_sha256 string, formatted_chars long"


def digests(formatted: DataFrame) -> DataFrame:
    """What the formatted text gives when it is read back."""

    def convert(batches: Iterator) -> Iterator:
        import pyarrow as pa

        for batch in batches:
            rows = []
            for text, mask in zip(batch.column(1), batch.column(2), strict=True):
                text = text.as_py()
                turns, loss = read_back(text), "".join(unescape(text[m["start"] : m["stop"]]) for m in mask.as_py())
                all_turns = hashlib.sha256("".join(f"{r}\n{t}\n" for r, t in turns).encode()).hexdigest()
                rows.append((len(turns), all_turns, len(loss), hashlib.sha256(loss.encode()).hexdigest(), len(text)))
            kinds = (pa.int64(), pa.string(), pa.int64(), pa.string(), pa.int64())
            yield pa.RecordBatch.from_arrays([batch.column(0), *(pa.array([r[k] for r in rows], t) for k, t in enumerate(kinds))], names=[c.split()[0] for c in DIGEST.split(", ")])

    return formatted.mapInArrow(convert, DIGEST)
