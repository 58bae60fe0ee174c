"""HTML extraction by a recurrent block labeller.

A page is a sequence of leaf blocks. Each block is a vector: hashed tags and class names of its path, hashed words,
and a few measures of shape. A bidirectional LSTM in numpy reads the whole sequence in both directions and
labels every block as main text or not. Pages are labelled in batches of similar length.

The model is trained when it is first asked for, on ``TRAIN_PAGES`` pages that ``sample_page`` makes up with
known labels: articles under several kinds of markup (semantic elements, named, oddly named and bare containers, tables for the
layout) beside menus, headers, footers, sidebars, notices,
adverts, forms and comments. Training is seeded and takes seconds; nothing is stored.

Defined cases: null or empty html: empty text; pages without main blocks: empty text; repeated rows are
labelled one by one, with null or repeated ids too; a very long page is one sequence of its own (its vectors are held at once, 512
bytes a block); blocks of equal text are judged by their places; an empty table gives an empty result; other columns aren't read, whatever their names.
"""

from __future__ import annotations

import random
import zlib
from collections.abc import Iterator
from functools import lru_cache

import numpy as np
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from coordloom.llm.html_blocks import Block, blocks_of

PATH_DIM, WORD_DIM, SHAPE_DIM, HIDDEN = 96, 24, 8, 16
DIM = PATH_DIM + WORD_DIM + SHAPE_DIM
TRAIN_PAGES = 1000
#: Share of the training pages without semantic elements.
LOOSE_SHARE = 0.35
EPOCHS = 14
BATCH = 32
SEED = 11


def vectors(blocks: list[Block]) -> np.ndarray:
    x = np.zeros((len(blocks), DIM), dtype=np.float32)
    for k, b in enumerate(blocks):
        for name in b.path:
            x[k, zlib.crc32(name.encode()) % PATH_DIM] = 1
        words = b.text.split()
        spots = np.bincount([zlib.crc32(w.encode()) % WORD_DIM for w in words], minlength=WORD_DIM)
        x[k, PATH_DIM : PATH_DIM + WORD_DIM] = spots / (4 + len(words))
        size = len(b.text)
        stops = sum(map(b.text.count, ".!?"))
        x[k, PATH_DIM + WORD_DIM :] = (np.log1p(size) / 8, np.log1p(len(words)) / 6, min(1.0, b.link_chars / size), min(1.0, 10 * stops / (1 + len(words))), b.text[-1] in ".!?\"'”", len(b.tags) / 10, k / len(blocks), 1)
    return x


class Labeller:
    """Two LSTMs and a logistic output; weights in ``self.w``."""

    def __init__(self, rng: np.random.Generator):
        def init(*shape: int) -> np.ndarray:
            return (rng.standard_normal(shape) / np.sqrt(shape[0])).astype(np.float32)

        self.w = {f"{k}{d}": v for d in "fb" for k, v in (("x", init(DIM, 4 * HIDDEN)), ("h", init(HIDDEN, 4 * HIDDEN)), ("c", np.zeros(4 * HIDDEN, np.float32)))}
        for d in "fb":
            self.w[f"c{d}"][HIDDEN : 2 * HIDDEN] = 1  # remember at first
        self.w["o"] = init(2 * HIDDEN + DIM, 1)
        self.w["oc"] = np.zeros(1, np.float32)

    def _run(self, x: np.ndarray, mask: np.ndarray, d: str) -> tuple[np.ndarray, list]:
        """x: (time, pages, DIM). Steps past a page's end keep its state."""
        steps, pages, _ = x.shape
        z, h, c, tape = x @ self.w[f"x{d}"] + self.w[f"c{d}"], np.zeros((pages, HIDDEN), np.float32), np.zeros((pages, HIDDEN), np.float32), []
        out = np.zeros((steps, pages, HIDDEN), np.float32)
        for t in range(steps) if d == "f" else range(steps - 1, -1, -1):
            g = z[t] + h @ self.w[f"h{d}"]
            i, f, o = (1 / (1 + np.exp(-np.clip(g[:, k * HIDDEN : (k + 1) * HIDDEN], -30, 30))) for k in range(3))
            u = np.tanh(g[:, 3 * HIDDEN :])
            m = mask[t][:, None]
            c_new = m * (f * c + i * u) + (1 - m) * c
            th = np.tanh(c_new)
            h_new = m * (o * th) + (1 - m) * h
            tape.append((t, i, f, o, u, c, h, th, m))
            c, h = c_new, h_new
            out[t] = h
        return out, tape

    def forward(self, x: np.ndarray, mask: np.ndarray) -> tuple[np.ndarray, tuple]:
        forth, tape_f = self._run(x, mask, "f")
        back, tape_b = self._run(x, mask, "b")
        joint = np.concatenate([forth, back, x], axis=2)
        logit = (joint @ self.w["o"])[:, :, 0] + self.w["oc"]
        return 1 / (1 + np.exp(-np.clip(logit, -30, 30))), (joint, tape_f, tape_b)

    def gradients(self, x: np.ndarray, mask: np.ndarray, y: np.ndarray) -> tuple[float, dict[str, np.ndarray]]:
        p, (joint, tape_f, tape_b) = self.forward(x, mask)
        n = mask.sum()
        loss = float(-(mask * (y * np.log(p + 1e-7) + (1 - y) * np.log(1 - p + 1e-7))).sum() / n)
        d_logit = (mask * (p - y) / n)[:, :, None].astype(np.float32)
        grads = {"o": np.einsum("tpk,tpo->ko", joint, d_logit), "oc": d_logit.sum(axis=(0, 1))}
        d_joint = d_logit @ self.w["o"].T
        for d, tape, part in (("f", tape_f, d_joint[:, :, :HIDDEN]), ("b", tape_b, d_joint[:, :, HIDDEN : 2 * HIDDEN])):
            wh, d_h, d_c = self.w[f"h{d}"], np.zeros_like(part[0]), np.zeros_like(part[0])
            d_z, g_h = np.zeros((*x.shape[:2], 4 * HIDDEN), np.float32), np.zeros_like(wh)
            for t, i, f, o, u, c, h, th, m in reversed(tape):
                total = d_h + part[t]
                through = m * total
                d_cell = m * d_c + through * o * (1 - th * th)
                gate = np.concatenate([d_cell * u * i * (1 - i), d_cell * c * f * (1 - f), through * th * o * (1 - o), d_cell * i * (1 - u * u)], axis=1)
                d_z[t] = gate
                g_h += h.T @ gate
                d_h = (1 - m) * total + gate @ wh.T
                d_c = d_cell * f + (1 - m) * d_c
            grads |= {f"h{d}": g_h, f"x{d}": np.einsum("tpk,tpg->kg", x, d_z), f"c{d}": d_z.sum(axis=(0, 1))}
        return loss, grads

    def label(self, pages: list[np.ndarray]) -> list[np.ndarray]:
        """Probability of main text for each block of each page; pages of similar length go together."""
        out: list[np.ndarray] = [np.zeros(0, np.float32)] * len(pages)
        order = sorted((k for k in range(len(pages)) if len(pages[k])), key=lambda k: len(pages[k]))
        lo = 0
        while lo < len(order):
            hi = lo + 1
            while hi < len(order) and hi - lo < 64 and len(pages[order[hi]]) * (hi - lo + 1) <= 20_000:
                hi += 1
            x, mask = _padded([pages[k] for k in order[lo:hi]])
            p, _ = self.forward(x, mask)
            for j, k in enumerate(order[lo:hi]):
                out[k] = p[: len(pages[k]), j]
            lo = hi
        return out


def _padded(pages: list[np.ndarray]) -> tuple[np.ndarray, np.ndarray]:
    steps = max(map(len, pages))
    x, mask = np.zeros((steps, len(pages), DIM), np.float32), np.zeros((steps, len(pages)), np.float32)
    for j, page in enumerate(pages):
        x[: len(page), j], mask[: len(page), j] = page, 1
    return x, mask


# Training pages

_SYLLABLES = "an be ci do el fa gro hi in ja ka lo mi nu or pe qui ra se ti un vo wes yl zu ment tion é ü ñ".split()


def _words(rng: random.Random, n: int) -> list[str]:
    return ["".join(rng.choices(_SYLLABLES, k=rng.choice((1, 1, 2, 2, 3, 4)))) for _ in range(n)]


def _sentence(rng: random.Random, n: int) -> str:
    words = _words(rng, n)
    if rng.random() < 0.06:
        words = [w + rng.choice(("***", "###", "%%%", "$$$", "&amp;&amp;")) for w in words]
    text = " ".join(words)
    return text[:1].upper() + text[1:] + rng.choice((".", ".", ".", "!", "?"))


def _paragraph(rng: random.Random) -> str:
    return " ".join(_sentence(rng, rng.choice((1, 2, 4, 8, 12, 20, 40))) for _ in range(rng.choice((1, 1, 2, 3, 6, 10))))


def sample_page(rng: random.Random) -> str:
    """A page whose main blocks hold the mark U+0001 at their start."""
    mark = "\x01"

    def link_list(kind: str) -> str:
        items = "".join(f'<li><a href="/{w}">{w}{rng.choice(("", "", ","))}</a></li>' for w in _words(rng, rng.randint(2, 9)))
        return rng.choice((f"<{kind}><ul>{items}</ul></{kind}>", f'<div class="{rng.choice(("menu", "navbar", "links", "breadcrumbs", "toc"))}"><ul>{items}</ul></div>'))

    def side(kind: str) -> str:
        body = "".join(f"<p>{_paragraph(rng)}</p>" if rng.random() < 0.5 else f'<div>{_sentence(rng, rng.randint(2, 12))}</div>' for _ in range(rng.randint(1, 3)))
        if kind == "ad":
            return f'<div class="{rng.choice(("ad", "advert", "ads banner", "sponsored", "promo"))}">{rng.choice((_sentence(rng, rng.randint(2, 16)), body))}</div>'
        if kind == "notice":
            return f'<div class="{rng.choice(("cookie notice", "consent", "banner", "newsletter", "popup", "notice"))}"><p>{_sentence(rng, rng.randint(5, 18))}</p><button>{_words(rng, 1)[0]}</button></div>'
        if kind == "form":
            return f"<form><label>{_sentence(rng, 3)}</label><input name=q><select><option>{_words(rng, 1)[0]}<option>{_words(rng, 1)[0]}</select><button>{_words(rng, 1)[0]}</button></form>"
        if kind == "comments":
            items = "".join(f'<div class="comment"><p>{_paragraph(rng)}</p></div>' for _ in range(rng.randint(1, 5)))
            return rng.choice((f'<section id="comments"><h3>{_sentence(rng, 2)}</h3>{items}</section>', f'<div class="comments">{items}</div>', f'<ol class="comment list">{items.replace("div", "li")}</ol>'))
        if kind == "footer":
            return f"<footer>&copy; {'.'.join(_words(rng, 3))} &middot; {_sentence(rng, rng.randint(2, 14))}</footer>" if rng.random() < 0.7 else f"<footer><p>{_sentence(rng, 6)}</p>{body}</footer>"
        if kind == "header":
            return f'<header><h1>{_sentence(rng, 3)}</h1><p>{_sentence(rng, 5)}</p></header>' if rng.random() < 0.5 else f'<header><div class="logo">{_words(rng, 1)[0]}</div>{link_list("nav")}</header>'
        return rng.choice((f"<aside>{body}</aside>", f'<div class="{rng.choice(("sidebar", "related", "widget", "share social"))}">{body}</div>'))

    title = _sentence(rng, rng.randint(1, 10))
    main = [f"<{rng.choice(('h1', 'h1', 'h2'))}>{mark}{title}</h1>"] if rng.random() < 0.9 else []
    for _ in range(rng.choice((1, 1, 2, 3, 5, 8, 13, 25, 50))):
        roll = rng.random()
        if roll < 0.1:
            main.append(f"<p><b>{mark}{_sentence(rng, rng.randint(1, 30))}<br>")
        elif roll < 0.8:
            main.append(f"<p>{mark}{_paragraph(rng)}" + rng.choice(("</p>", "</p>", "</p>", "")))
        elif roll < 0.85:
            main.append(f"<h2>{mark}{_sentence(rng, rng.randint(1, 5))}</h2>")
        elif roll < 0.9:
            main.append("<ul>" + "".join(f"<li>{mark}{_sentence(rng, rng.randint(2, 12))}</li>" for _ in range(rng.randint(2, 5))) + "</ul>")
        elif roll < 0.94:
            main.append(f"<blockquote>{mark}{_paragraph(rng)}</blockquote>")
        elif roll < 0.97:
            main.append("<table><tr>" + "".join(f"<td>{mark}{_words(rng, 1)[0]}</td>" for _ in range(3)) + "</tr></table>")
        else:
            main.append(side(rng.choice(("ad", "notice", "form"))))
    def box(*names: str) -> tuple[str, str]:
        """A container under names of its kind, under made-up ones, or without any."""
        roll, tag = rng.random(), rng.choice(("div", "div", "div", "section"))
        name = rng.choice(("-", " ", "_")).join(rng.sample(names, rng.randint(1, 2))) if roll < 0.6 else _words(rng, 1)[0] if roll < 0.75 else ""
        return (f'<{tag} {rng.choice(("class", "class", "id"))}="{name}">' if name else f"<{tag}>", f"</{tag}>")

    opening, closing = rng.choice((("<article>", "</article>"), ("<article>", "</article>"), ("<article>", "</article>"), ("<main>", "</main>"), ("<main><article>", "</article></main>"), ('<div class="content">', "</div>"), ('<div id="post"><div class="entry body">', "</div></div>"), ('<section class="article text">', "</section>")))
    before = [side(rng.choice(("ad", "notice", "header", "aside", "form"))) for _ in range(rng.choice((0, 1, 1, 2)))]
    after = [side(rng.choice(("ad", "comments", "comments", "aside", "notice", "form"))) for _ in range(rng.choice((0, 0, 1, 2)))]
    if rng.random() < 0.85:
        before.insert(rng.randint(0, len(before)), link_list("nav"))
    if rng.random() < 0.9:
        after.append(side("footer"))
    if rng.random() < LOOSE_SHARE:  # pages without semantic elements: bare or oddly named containers, or a table for the layout
        opening, closing = box("story", "content", "post", "text", "entry", "body", "main", "article", "copy", "prose", "page")
        if rng.random() < 0.4:
            outer = box("wrap", "container", "main", "page", "layout", "column", "inner")
            opening, closing = outer[0] + opening, closing + outer[1]
        items = lambda: "".join(rng.choice((f'<a href="/{w}">{w}</a> ', f'<li><a href="/{w}">{w}</a></li>')) for w in _words(rng, rng.randint(2, 9)))
        menu = box("menu", "nav", "top", "links", "site", "bar", "header")
        bottom = box("footer", "bottom", "copyright", "legal", "site", "foot")
        before = [menu[0] + items() + menu[1], *before] if rng.random() < 0.8 else before
        after = [*after, f"{bottom[0]}&copy; {_sentence(rng, rng.randint(2, 9))}{bottom[1]}"] if rng.random() < 0.8 else after
        if rng.random() < 0.3:
            opening, closing = "<table><tr><td>" + items() + "</td><td>" + (opening if rng.random() < 0.5 else ""), "</td>" + (f"<td>{items()}</td>" if rng.random() < 0.5 else "") + "</tr></table>"
    page = f'<!DOCTYPE html><html lang="xx"><head><meta charset="utf-8"><title>{title}</title><style>p{{margin:0}}</style><script>var t="</p>";</script></head><body>' + "".join(before) + opening + "".join(main) + closing + "".join(after)
    return page + "</body></html>" if rng.random() < 0.8 else page


def labelled(source: str) -> tuple[np.ndarray, np.ndarray]:
    """(vectors, labels) of a page with marks."""
    blocks = blocks_of(source)
    labels = np.array([b.text.startswith("\x01") for b in blocks], dtype=np.float32)
    for b in blocks:
        b.text = b.text.lstrip("\x01") or "-"
    return vectors(blocks), labels


@lru_cache(maxsize=1)
def trained(n_pages: int = TRAIN_PAGES, epochs: int = EPOCHS, seed: int = SEED) -> Labeller:
    pages, rng = random.Random(seed), np.random.default_rng(seed)
    data = sorted((labelled(sample_page(pages)) for _ in range(n_pages)), key=lambda d: len(d[0]))
    batches = []
    for lo in range(0, len(data), BATCH):
        part = data[lo : lo + BATCH]
        x, mask = _padded([d[0] for d in part])
        y = np.zeros_like(mask)
        for j, d in enumerate(part):
            y[: len(d[1]), j] = d[1]
        batches.append((x, mask, y))
    model = Labeller(rng)
    m, v, step = {k: 0 * w for k, w in model.w.items()}, {k: 0 * w for k, w in model.w.items()}, 0
    for epoch in range(epochs):
        rate = 0.01 * 0.5 ** (epoch / 5)
        for k in rng.permutation(len(batches)):
            _, grads = model.gradients(*batches[k])
            norm = np.sqrt(sum(float((g * g).sum()) for g in grads.values()))
            step += 1
            for name, g in grads.items():
                g = g * min(1.0, 5.0 / (norm + 1e-9))
                m[name] = 0.9 * m[name] + 0.1 * g
                v[name] = 0.999 * v[name] + 0.001 * g * g
                model.w[name] = (model.w[name] - rate * (m[name] / (1 - 0.9**step)) / (np.sqrt(v[name] / (1 - 0.999**step)) + 1e-8)).astype(np.float32)
    return model


def extract(pages: list[str], model: Labeller) -> list[tuple[str, int, int]]:
    """(main text, blocks, main blocks) of each page."""
    found = [blocks_of(p) for p in pages]
    scores = model.label([vectors(b) if b else np.zeros((0, DIM), np.float32) for b in found])
    out = []
    for blocks, score in zip(found, scores, strict=True):
        main = [b.text for b, s in zip(blocks, score, strict=True) if s >= 0.5]
        out.append(("\n".join(main), len(blocks), len(main)))
    return out


def extract_main_text(pages: DataFrame, page_id: str = "page_id", url: str = "url", html: str = "html") -> DataFrame:
    """(page_id, url, text, n_chars, n_blocks, n_main) per row."""
    weights = trained().w

    def run(batches: Iterator) -> Iterator:
        import pyarrow as pa

        model = Labeller(np.random.default_rng(0))
        model.w = weights
        for batch in batches:
            for lo in range(0, batch.num_rows, 128):
                part = batch.slice(lo, 128)
                rows = extract([x or "" for x in part.column(2).to_pylist()], model)
                yield pa.RecordBatch.from_arrays([part.column(0), part.column(1), pa.array([r[0] for r in rows], pa.string()), *(pa.array(c, pa.int64()) for c in ([len(r[0]) for r in rows], [r[1] for r in rows], [r[2] for r in rows]))], names=["page_id", "url", "text", "n_chars", "n_blocks", "n_main"])

    source = pages.select(F.col(f"`{page_id}`").cast("long").alias("page_id"), F.col(f"`{url}`").cast("string").alias("url"), F.col(f"`{html}`").cast("string").alias("html"))
    return source.mapInArrow(run, "page_id long, url string, text string, n_chars long, n_blocks long, n_main long")
