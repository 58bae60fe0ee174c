"""Leaf blocks of an HTML text: a forgiving tokenizer that keeps the tag path of each block."""

from __future__ import annotations

import html
import re
from dataclasses import dataclass, field

#: Fixed names: elements that start a block of their own, and elements whose content is never text.
BLOCKS = frozenset("address article aside blockquote body button caption dd details dialog div dl dt fieldset figcaption figure footer form h1 h2 h3 h4 h5 h6 head header hgroup hr html label legend li main menu nav ol option p pre section select summary table tbody td textarea tfoot th thead title tr ul".split())
RAW = frozenset(("script", "style", "noscript", "template", "iframe", "svg", "object", "canvas"))
VOID = frozenset(("hr", "br", "img", "meta", "link", "input", "area", "base", "col", "embed", "source", "track", "wbr"))
#: An open element of the left kind ends where one of the right kinds begins.
ENDS_AT = {"p": BLOCKS, "li": frozenset(("li",)), "dt": frozenset(("dt", "dd")), "dd": frozenset(("dt", "dd")), "option": frozenset(("option",)), "tr": frozenset(("tr",)), "td": frozenset(("td", "th", "tr")), "th": frozenset(("td", "th", "tr")), "head": frozenset(("body",)), "title": BLOCKS}

_TOKEN = re.compile(r"<!--.*?(?:-->|\Z)|<(/?)([a-zA-Z][^\s/>]*+)((?:[^>\"']++|\"[^\"]*+\"|'[^']*+')*+)(?:>|\Z)|<(/?)([a-zA-Z][^\s/>]*+)([^>]*+)(?:>|\Z)|<[!?/][^>]*+(?:>|\Z)", re.S)
_CLASS = re.compile(r"(?:class|id|role)\s*=\s*(?:\"([^\"]*)\"|'([^']*)'|([^\s>]+))", re.I)
_BLANK = re.compile(r"\s+")


@dataclass
class Block:
    path: tuple[str, ...]  # tags and class or id names from the outside in
    text: str
    link_chars: int
    tags: tuple[str, ...] = field(default=())


def blocks_of(source: str) -> list[Block]:
    """The blocks with text, in order. White space inside a block is one blank; ``br`` counts as white space."""
    out: list[Block] = []
    stack: list[tuple[str, tuple[str, ...]]] = []
    parts: list[str] = []
    links, in_link, at, n = 0, 0, 0, len(source)

    def add(text: str) -> None:
        nonlocal links
        if text:
            parts.append(text)
            if in_link:
                links += len(text)

    def flush() -> None:
        nonlocal links
        text = _BLANK.sub(" ", html.unescape("".join(parts))).strip()
        if text:
            out.append(Block(tuple(x for _, names in stack for x in names), text, links, tuple(t for t, _ in stack)))
        parts.clear()
        links = 0

    while at < n:
        m = _TOKEN.search(source, at)
        if m is None:
            add(source[at:])
            break
        add(source[at : m.start()])
        at = m.end()
        name = m[2] or m[5]
        if not name:
            continue
        name, closing, attributes = name.lower(), bool(m[1] or m[4]), m[3] if m[2] else m[6]
        if name == "br":
            add(" ")
        elif name == "a":
            in_link = 0 if closing else 1
        elif name in RAW:
            if not closing and not (attributes or "").rstrip().endswith("/"):
                end = re.compile(f"</{name}", re.I).search(source, at)
                at = end.start() if end else n
        elif name in BLOCKS:
            flush()
            if closing:
                for k in range(len(stack) - 1, -1, -1):
                    if stack[k][0] == name:
                        del stack[k:]
                        break
            else:
                while stack and name in ENDS_AT.get(stack[-1][0], ()):
                    stack.pop()
                if name not in VOID:
                    words = [w.lower() for c in _CLASS.finditer(attributes or "") for w in re.split(r"[^a-zA-Z]+", c[1] or c[2] or c[3] or "") if w]
                    stack.append((name, (name, *words)))
    flush()
    return out
