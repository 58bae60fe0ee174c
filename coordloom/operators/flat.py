"""Passes over rows as flat arrays: nothing is done row by row, and the steps of a chunk are solved together.

A step depends on those before it only through w, by at most scale |x|^2 each. Where that is little over a chunk, the
chunk's steps are the one solution of a triangular system, found by sweeps over the whole chunk until nothing moves in the last
digits: the same steps as one after another. Elsewhere (few examples, many workers) they are taken one by one (``kernels.step_block``).
"""

from __future__ import annotations

from collections.abc import Iterator
from copy import copy
from dataclasses import replace

import numpy as np

from coordloom.operators import losses, permute
from coordloom.operators.kernels import Block, Sweep, _share, dual_pass, lists, step_block

#: Examples of a chunk that is solved together, at most and at least.
MOST, LEAST = 4096, 48
#: The same at most for dense examples of more than NARROW columns: their Gram matrix, and their rounds, grow with it.
MOST_WIDE, MOST_WIDE_RACE = 128, 512
#: How far the steps of a chunk may move each other's margins in sum.
COUPLING = 1.5
#: Sweeps over a chunk; one that still moves then is stepped one by one.
SWEEPS = 60
SETTLED = 1e-14
#: Newton moves of each step before the first sweep; later ones have one each.
INNER = 2
#: Columns up to which dense examples keep running sums by column; above it their Gram matrix is smaller.
NARROW = 24
#: Columns up to which the lock-free rounds are solved together.
RACE_COLUMNS = 128


class Rows:
    """Rows as flat arrays: ``at`` cuts the examples into rows, ``indptr`` the values into examples."""

    def __init__(self, slot, gid, bid, wid, at, indptr, idx, val, y, old):
        self.slot, self.gid, self.bid, self.wid, self.at, self.indptr, self.idx, self.val, self.y, self.old = slot, gid, bid, wid, at, indptr, idx, val, y, old
        self.alpha = old.copy()
        sizes = np.diff(indptr)
        self.width = int(sizes[0]) if len(sizes) and (sizes == sizes[0]).all() else None  # of every example, if it is one
        self.q = np.einsum("ij,ij->i", *[val.reshape(-1, self.width)] * 2) if self.width else np.bincount(np.repeat(np.arange(len(y)), sizes), weights=val * val, minlength=len(y))
        self.largest = float(self.q.max()) if len(self.q) else 0.0

    @property
    def num_rows(self) -> int:
        return len(self.bid)

    @staticmethod
    def of(batch) -> Rows:
        if isinstance(batch, Rows):
            return batch
        names = batch.schema.names
        (p_at, p), (v_at, v), (y_at, y) = (lists(batch.column(c)) for c in ("indptr", "val", "y"))
        p, v, y = p[p_at[0] : p_at[-1]], v[v_at[0] : v_at[-1]], y[y_at[0] : y_at[-1]]
        between = np.ones(max(0, len(p) - 1), dtype=bool)
        between[p_at[1:-1] - p_at[0] - 1] = False
        sizes, idx = np.diff(p)[between], None
        if not batch.column("idx").null_count:
            i_at, i = lists(batch.column("idx"))
            idx = i[i_at[0] : i_at[-1]]
        from coordloom.operators.kernels import alphas_of

        wid = np.asarray(batch.column("wid")) if "wid" in names else None
        indptr = np.concatenate(([0], np.cumsum(sizes, dtype=np.int64)))
        return Rows(*(np.asarray(batch.column(c)) for c in ("slot", "gid", "bid")), wid, (y_at - y_at[0]).astype(np.int64), indptr, idx, v, y, np.array(alphas_of(batch, len(y))))

    @staticmethod
    def join(parts: list[Rows]) -> Rows:
        if len(parts) == 1:
            return parts[0]
        one = lambda name: np.concatenate([getattr(p, name) for p in parts])
        cuts = lambda name: np.concatenate(([0], np.cumsum(np.concatenate([np.diff(getattr(p, name)) for p in parts]))))
        out = Rows(one("slot"), one("gid"), one("bid"), None if parts[0].wid is None else one("wid"), cuts("at"), cuts("indptr"), None if parts[0].idx is None else one("idx"), one("val"), one("y"), one("old"))
        out.alpha = one("alpha")
        return out

    @staticmethod
    def gather(parts: Iterator[Rows], n: int, cells: int) -> Rows | None:
        """``join`` of parts as they come into arrays for ``n`` examples and ``cells`` values, so that they are held once; grows if more come."""
        flat, small = {}, []
        m = e = 0
        for p in parts:
            small.append((p.slot, p.gid, p.bid, p.wid, np.diff(p.at), np.diff(p.indptr)))
            for name in ("y", "old", "val", "idx"):
                new = getattr(p, name)
                if new is None:
                    continue
                lo, room = (e, cells) if name in ("val", "idx") else (m, n)
                if name not in flat:
                    flat[name] = np.empty(max(room, len(new)), new.dtype)
                elif lo + len(new) > len(flat[name]):
                    flat[name] = np.concatenate((flat[name], np.empty(lo + len(new), new.dtype)))
                flat[name][lo : lo + len(new)] = new
            m, e = m + len(p.y), e + len(p.val)
        if not small:
            return None
        slot, gid, bid, wid, at, sizes = (None if c[0] is None else np.concatenate(c) for c in zip(*small, strict=True))
        cuts = lambda sizes: np.concatenate(([0], np.cumsum(sizes)))
        return Rows(slot, gid, bid, wid, cuts(at), cuts(sizes), flat["idx"][:e] if "idx" in flat else None, flat["val"][:e], flat["y"][:m], flat["old"][:m])

    def apart(self, bucket: int, slab: int) -> Rows:
        """These slabs as rows of ``bucket`` examples, ``slab`` of them each but in the last; views of the same values."""
        counts = -(-np.diff(self.at) // bucket)
        of = np.repeat(np.arange(len(counts)), counts)
        k = np.arange(len(of)) - np.repeat(np.cumsum(counts) - counts, counts)
        out = copy(self)
        out.slot, out.gid, out.bid, out.wid = self.slot[of], self.gid[of], self.bid[of] * slab + k, None
        out.at = np.append(self.at[:-1][of] + k * bucket, self.at[-1])
        return out

    def tail(self, k: int) -> Rows:
        """The rows from k on."""
        lo = self.at[k]
        e = self.indptr[lo]
        out = Rows(self.slot[k:], self.gid[k:], self.bid[k:], None if self.wid is None else self.wid[k:], self.at[k:] - lo, self.indptr[lo:] - e, None if self.idx is None else self.idx[e:], self.val[e:], self.y[lo:], self.old[lo:])
        out.alpha = self.alpha[lo:].copy()
        return out

    def examples(self, rows: np.ndarray, sweep: Sweep) -> np.ndarray:
        """The examples of these rows one row after another, each row's buckets of ``unit`` in drawn order."""
        sizes = self.at[rows + 1] - self.at[rows]
        ends = np.cumsum(sizes)
        take = np.repeat(self.at[rows] - ends + sizes, sizes) + np.arange(int(ends[-1]) if len(ends) else 0)
        if sweep.ordered or not sweep.unit:
            return take
        for r, lo, m in zip(rows.tolist(), (ends - sizes).tolist(), sizes.tolist(), strict=True):
            if sweep.unit < m:
                drawn = np.random.default_rng((sweep.seed, int(self.bid[r]))).permutation(-(-m // sweep.unit))
                places = (drawn[:, None] * sweep.unit + np.arange(sweep.unit)).ravel()
                take[lo : lo + m] = self.at[r] + places[places < m]
        return take

    def entries(self, take: np.ndarray) -> tuple[np.ndarray, np.ndarray]:
        """(place in ``take``, place in ``val``) of every value of these examples."""
        if self.width:
            return np.repeat(np.arange(len(take)), self.width), (take[:, None] * self.width + np.arange(self.width)).ravel()
        starts, sizes = self.indptr[take], self.indptr[take + 1] - self.indptr[take]
        ends = np.cumsum(sizes)
        return np.repeat(np.arange(len(take)), sizes), np.repeat(starts - ends + sizes, sizes) + np.arange(int(ends[-1]) if len(ends) else 0)

    def dense(self, take: np.ndarray, d: int) -> np.ndarray:
        if self.idx is None:
            return self.val.reshape(len(self.y), -1)[take]
        x, (row, e) = np.zeros((len(take), d)), self.entries(take)
        x[row, self.idx[e]] = self.val[e]
        return x

    def blocks(self) -> Iterator[Block]:
        """The rows as blocks of their own alpha and views of the rest."""
        for k, (lo, hi) in enumerate(zip(self.at[:-1].tolist(), self.at[1:].tolist(), strict=True)):
            b, e, f = Block(), self.indptr[lo], self.indptr[hi]
            b.slot, b.gid, b.bid, b.wid = int(self.slot[k]), int(self.gid[k]), int(self.bid[k]), -1 if self.wid is None else int(self.wid[k])
            b.y, b.indptr, b.val, b.idx = self.y[lo:hi], self.indptr[lo : hi + 1] - e, self.val[e:f], None if self.idx is None else self.idx[e:f]
            b.old = self.alpha[lo:hi].copy()
            b.alpha = b.old.copy()
            yield b

    def drawn(self, rows: np.ndarray, seed: int) -> np.ndarray:
        """The examples of these rows one row after another, each row's in drawn order."""
        sizes = self.at[rows + 1] - self.at[rows]
        take = np.repeat(self.at[rows] - np.cumsum(sizes) + sizes, sizes) + np.arange(int(sizes.sum()))
        return take[permute.inside_rows(self.bid[rows], sizes, seed)]

    def block(self, take: np.ndarray) -> Block:
        """These examples as one row; its alpha is a copy."""
        out, (row, e) = Block(), self.entries(take)
        out.bid = out.gid = out.slot = out.wid = 0
        out.y, out.val, out.idx, out.alpha = self.y[take], self.val[e], None if self.idx is None else self.idx[e], self.alpha[take]
        out.old, out.indptr = out.alpha, np.concatenate(([0], np.cumsum(np.bincount(row, minlength=len(take)))))
        return out


def settle(loss: str, q: np.ndarray, y: np.ndarray, a: np.ndarray, s: np.ndarray, margins, sweeps: int = SWEEPS) -> np.ndarray | None:
    """The steps of a chunk: those whose own margins, ``margins(steps)``, lead to them; ``margins(None)`` are those of no steps. None if they don't settle."""
    b = y * a
    if loss != "logistic":
        delta = np.zeros_like(y)
        for _ in range(sweeps):
            new = losses.step(loss, margins(delta), q, y, a, s)
            moved = np.abs(new - delta) > SETTLED * (1.0 + np.abs(new))
            delta = new
            if not moved.any():
                return delta
        return None
    with np.errstate(divide="ignore", over="ignore"):
        t = y * margins(None)
        inside = (b > 0.0) & (b < 1.0)
        u = np.log(b / (1.0 - b)) if inside.all() else np.where(inside, np.log(b / (1.0 - b)), -t)
        p, last = 1.0 / (1.0 + np.exp(-u)), np.inf
        for k in range(sweeps):
            if k:
                t = y * margins(y * (p - b))
            before = u
            for _ in range(1 if k else INNER):  # each step by itself, its margin held
                u = u - (u + t + s * (p - b)) / (1.0 + s * p * (1.0 - p))
                p = 1.0 / (1.0 + np.exp(-u))
            moved = float((np.abs(u - before) / (1.0 + np.abs(u))).max())
            if moved <= SETTLED or k > 1 and moved < last and moved * (moved / last) <= 0.1 * SETTLED:  # moves shrink faster and faster
                return y * (p - b)
            last = moved
    return None


def chunk_size(sweep: Sweep, largest: float, rounds: int = 1) -> int:
    """Examples whose steps may be solved together: 0 if too few."""
    if not sweep.shared_updates:
        return MOST
    each = sweep.sigma / (sweep.lam * sweep.n) * largest * (0.25 if sweep.loss == "logistic" else 1.0 if sweep.loss == "ridge" else 2.0)
    m = int(COUPLING / each) * rounds if each > 0 else MOST
    return 0 if m < LEAST else min(m, MOST)


def most(rows: Rows, d: int, wide: int = MOST_WIDE) -> int:
    return wide if rows.idx is None and d > NARROW else MOST


def step_examples(sweep: Sweep, rows: Rows, take: np.ndarray, w: np.ndarray, step) -> None:
    """Exact steps on these examples in this order; changes ``rows.alpha`` and the replica ``w``."""
    size = min(chunk_size(sweep, rows.largest), most(rows, len(w)))
    if not size:
        one_by_one(sweep, rows, take, w, step)
        return
    for lo in range(0, len(take), size):
        now = take[lo : lo + size]
        if not _chunk(sweep, rows, now, w):
            one_by_one(sweep, rows, now, w, step)


def one_by_one(sweep: Sweep, rows: Rows, take: np.ndarray, w: np.ndarray, step) -> None:
    b = rows.block(take)
    step_block(replace(sweep, ordered=True), b, w, step)
    rows.alpha[take] = b.alpha


class Chunk:
    """Examples in order: ``earlier(c)`` gives each one's product with the sum of c x over those before it, ``add`` the whole sum."""

    def __init__(self, rows: Rows, take: np.ndarray, d: int):
        self.m, self.dense, self.before = len(take), rows.idx is None, None
        if self.dense:
            self.x = rows.val.reshape(len(rows.y), -1)[take]
            if d <= NARROW:
                self.columns = np.ascontiguousarray(self.x.T)
            return
        row, e = rows.entries(take)
        col, val = rows.idx[e], rows.val[e]
        order = np.argsort(col.astype(np.uint16) if d <= 1 << 16 else col, kind="stable")  # by column, inside by example
        self.col, self.row = col.take(order), row.take(order)
        self.val = None if (val == 1.0).all() else val.take(order)  # None: all ones
        self.first = np.flatnonzero(np.concatenate(([True], self.col[1:] != self.col[:-1]))) if len(col) else np.empty(0, np.int64)
        self.counts, self.sums = np.diff(np.append(self.first, len(col))), np.zeros(len(col) + 1)

    def margins(self, w: np.ndarray) -> np.ndarray:
        if self.dense:
            return self.x @ w
        own = w.take(self.col)
        return np.bincount(self.row, weights=own if self.val is None else own * self.val, minlength=self.m)

    def earlier(self, c: np.ndarray) -> np.ndarray:
        if not self.dense:
            own = c.take(self.row)
            if self.val is not None:
                own *= self.val
            np.cumsum(own, out=self.sums[1:])
            before = np.subtract(self.sums[:-1], np.repeat(self.sums.take(self.first), self.counts), out=own)
            if self.val is not None:
                before *= self.val
            return np.bincount(self.row, weights=before, minlength=self.m)
        if self.x.shape[1] <= NARROW:
            out = np.zeros(self.m)
            out[1:] = np.einsum("ij,ij->j", self.columns[:, 1:], np.cumsum(self.columns * c, axis=1)[:, :-1])
            return out
        if self.before is None:
            self.before = np.tril(self.x @ self.x.T, -1)
        return self.before @ c

    def add(self, w: np.ndarray, c: np.ndarray) -> None:
        if self.dense:
            w += c @ self.x
        elif len(self.first):
            own = c.take(self.row)
            w[self.col[self.first]] += np.add.reduceat(own if self.val is None else own * self.val, self.first)


def _chunk(sweep: Sweep, rows: Rows, take: np.ndarray, w: np.ndarray) -> bool:
    scale, q, y, a = sweep.sigma / (sweep.lam * sweep.n), rows.q[take], rows.y[take], rows.alpha[take]
    chunk = Chunk(rows, take, len(w))
    z = chunk.margins(w)
    delta = settle(sweep.loss, q, y, a, q * scale, (lambda c: z if c is None else z + chunk.earlier(scale * c)) if sweep.shared_updates else lambda _: z)
    if delta is None:
        return False
    rows.alpha[take] = a + delta
    if sweep.shared_updates:
        chunk.add(w, scale * delta)
    return True


def fixed_point(f, m: int) -> np.ndarray | None:
    """x with x = f(x), where an entry of f(x) depends on earlier ones of x alone; None if it doesn't settle."""
    x = f(np.zeros(m))
    for _ in range(SWEEPS):
        new = f(x)
        if not (np.abs(new - x) > SETTLED * (1.0 + np.abs(new))).any():
            return new
        x = new
    return None


class DualPass:
    """``kernels.dual_pass`` by chunks."""

    def __init__(self, sweep: Sweep):
        self.sweep, self.plain = sweep, dual_pass(sweep)

    @property
    def extremes(self) -> tuple[float, float]:
        return self.plain.extremes

    def __call__(self, rows: Rows, take: np.ndarray, w: np.ndarray) -> None:
        size = min(chunk_size(self.sweep, rows.largest), most(rows, len(w))) if self.sweep.loss == "logistic" else 0  # bounded losses jump where they leave out
        for lo in range(0, len(take), size or MOST):
            now = take[lo : lo + (size or MOST)]
            if not size or not self.chunk(rows, now, w):
                b = rows.block(now)
                self.plain(b, w, np.arange(len(now)))
                rows.alpha[now] = b.alpha

    def chunk(self, rows: Rows, take: np.ndarray, w: np.ndarray) -> bool:
        s = self.sweep
        scale, y, a = s.sigma / (s.lam * s.n), rows.y[take], rows.alpha[take]
        curved, chunk, threshold = rows.q[take] * scale, Chunk(rows, take, len(w)), s.shrink[0] if s.shrink else 0.0
        z, old, near = chunk.margins(w), y * a, max(1e-10, 0.1 * threshold)
        start = np.clip(old, 1e-8, 1.0 - 1e-8)
        at_start = curved * (start - old) + np.log(start / (1.0 - start))
        worst = 0.0

        def steps(delta: np.ndarray) -> np.ndarray:
            nonlocal worst
            margin, b = y * (z + chunk.earlier(scale * delta)), start
            slope = margin + at_start
            size = np.abs(slope)
            worst, asked = float(size.max()), size > threshold
            live = asked
            for _ in range(self.plain.INNER):
                if not live.any():
                    break
                new = b - slope / (curved + 1.0 / (b * (1.0 - b)))
                new = np.where(new <= 0.0, 0.1 * b, np.where(new >= 1.0, 1.0 - 0.1 * (1.0 - b), new))
                b = np.where(live, new, b)
                slope = margin + curved * (b - old) + np.log(b / (1.0 - b))
                live = live & (np.abs(slope) > near)
            return np.where(asked, y * (b - old), 0.0)

        delta = fixed_point(steps, len(take))
        if delta is None:
            return False
        self.plain.extremes = (max(self.plain.extremes[0], worst), 0.0)
        rows.alpha[take] = a + delta
        chunk.add(w, scale * delta)
        return True


class Gradients:
    """``kernels.sag_sweep`` and ``kernels.sgd_sweep`` by chunks: between two steps w only shrinks and moves along known vectors, so a chunk's margins
    follow from the slopes of the examples before, whose one solution is found as for coordinate steps."""

    #: How far w may shrink over a chunk.
    SHRUNK = 0.05

    def __init__(self, sweep: Sweep, w0: np.ndarray, average: np.ndarray | None):
        self.sweep, self.w0, self.w, self.average = sweep, w0, w0.copy(), average
        self.g = None if average is None else average.copy()
        self.t = 0
        self.curved = 0.25 if sweep.loss == "logistic" else 1.0 if sweep.loss == "ridge" else 2.0

    def size(self, rows: Rows) -> int:
        """Examples of the next chunk: 0 if too few."""
        s, each = self.sweep, self.curved * rows.largest
        if s.kind == "sgd":
            m = COUPLING / max(1e-300, each * self.rate(self.t))
        else:
            each *= 1.0 / s.n
            m = max((COUPLING / max(1e-300, each * s.rate)) ** 0.5, COUPLING * s.lam / max(1e-300, each))
            shrink = s.rate * s.lam
            m = min(m, np.log(self.SHRUNK) / np.log1p(-shrink)) if 0.0 < shrink < 1.0 else 0
        return 0 if m < LEAST else int(min(m, most(rows, len(self.w))))

    def rate(self, t):
        return self.sweep.rate / (1 + self.sweep.rate * self.sweep.lam * t)

    def over(self, rows: Rows, take: np.ndarray) -> None:
        lo = 0
        while lo < len(take):
            size = self.size(rows)
            now = take[lo : lo + (size or MOST)]
            if not size or not (self._sgd if self.sweep.kind == "sgd" else self._sag)(rows, now):
                self._one_by_one(rows, now)
            lo += len(now)
            self.t += len(now)

    def _one_by_one(self, rows: Rows, take: np.ndarray) -> None:
        s, b = self.sweep, rows.block(take)
        for k in range(len(take)):
            c, x = slice(None) if b.idx is None else b.idx[b.indptr[k] : b.indptr[k + 1]], b.val[b.indptr[k] : b.indptr[k + 1]]
            new = float(losses.slope(s.loss, float(self.w[c] @ x), b.y[k]))
            if s.kind == "sgd":
                rate = self.rate(self.t + k)
                self.w *= 1 - rate * s.lam
                self.w[c] -= rate * new * x
            else:
                self.g[c] += (new - b.alpha[k]) / s.n * x
                b.alpha[k] = new
                self.w -= s.rate * (self.g + s.lam * self.w)
        if s.kind == "sag":
            rows.alpha[take] = b.alpha

    def _sgd(self, rows: Rows, take: np.ndarray) -> bool:
        s, m, y, chunk = self.sweep, len(take), rows.y[take], Chunk(rows, take, len(self.w))
        rate = self.rate(self.t + np.arange(m))
        shrunk = np.cumprod(1.0 - rate * s.lam)  # after each step
        if shrunk[-1] < self.SHRUNK:
            return False
        z, held, share = chunk.margins(self.w), np.concatenate(([1.0], shrunk[:-1])), rate / shrunk
        slopes = fixed_point(lambda g: losses.slope(s.loss, held * (z - chunk.earlier(share * g)), y), m)
        if slopes is None:
            return False
        chunk.add(self.w, -share * slopes)
        self.w *= shrunk[-1]
        return True

    def _sag(self, rows: Rows, take: np.ndarray) -> bool:
        s, m, y, a, chunk = self.sweep, len(take), rows.y[take], rows.alpha[take], Chunk(rows, take, len(self.w))
        left = (1.0 - s.rate * s.lam) ** np.arange(m + 1)  # of w after so many steps
        start = left[:-1] * chunk.margins(self.w) - (1.0 - left[:-1]) / s.lam * chunk.margins(self.g)

        def slopes(new: np.ndarray) -> np.ndarray:
            c = (new - a) / s.n
            return losses.slope(s.loss, start - (chunk.earlier(c) - left[:-1] * chunk.earlier(c / left[:-1])) / s.lam, y)

        new = fixed_point(slopes, m)
        if new is None:
            return False
        c = (new - a) / s.n
        self.w *= left[-1]
        self.w -= (1.0 - left[-1]) / s.lam * self.g
        chunk.add(self.w, -c * (1.0 - left[-1] / left[:-1]) / s.lam)
        chunk.add(self.g, c)
        rows.alpha[take] = new
        return True

    def end(self, slot: int) -> list[tuple]:
        moves = [(0, slot, -1, -1, self.w - self.w0)] + ([] if self.g is None else [(2, slot, -1, -1, self.g - self.average)])
        return [(*r, 0.0, 0.0, 0.0, 0.0) for r in moves]


def gradient_batches(sweep: Sweep, w0: np.ndarray, average: np.ndarray | None, batches: Iterator) -> Iterator:
    """``kernels.sag_sweep`` or ``kernels.sgd_sweep`` over Arrow batches."""
    run, slot = Gradients(sweep, w0, average), 0
    for batch in batches:
        if not batch.num_rows:
            continue
        rows = Rows.of(batch)
        run.over(rows, rows.examples(np.arange(len(rows.bid)), sweep))
        if sweep.kind == "sag":
            slot = int(rows.slot[-1])
            yield from alpha_batches(rows)
    yield from run.end(slot)


def alpha_batch(rows: Rows, lo: int, hi: int):
    """Rows lo to hi as a batch of kernels.OUT of kind 1."""
    import pyarrow as pa

    m, zeros = hi - lo, np.zeros(hi - lo)
    at = rows.at[lo : hi + 1]
    vec = pa.ListArray.from_arrays(pa.array((at - at[0]).astype(np.int32)), pa.array(rows.alpha[at[0] : at[-1]]))
    columns = [pa.array(np.ones(m, np.int32)), pa.array(rows.slot[lo:hi].astype(np.int32)), pa.array(rows.gid[lo:hi].astype(np.int32)), pa.array(rows.bid[lo:hi].astype(np.int64)), vec, *[pa.array(zeros)] * 4]
    return pa.RecordBatch.from_arrays(columns, names=["kind", "slot", "gid", "bid", "vec", "s0", "s1", "s2", "s3"])


def alpha_batches(rows: Rows, count: int | None = None) -> Iterator:
    """The alpha of all rows, or of the first ones, in batches of about two megabytes."""
    lo, count = 0, len(rows.bid) if count is None else count
    while lo < count:
        hi = max(lo + 1, int(np.searchsorted(rows.at, rows.at[lo] + (1 << 18), side="right")) - 1)
        hi = min(count, hi, lo + (1 << 15))
        yield alpha_batch(rows, lo, hi)
        lo = hi


class Pass:
    """One pass of all workers of a group over its rows, piece by piece; see ``kernels.coordinate_sweep``."""

    def __init__(self, sweep: Sweep, w0: np.ndarray):
        self.sweep, self.w0, self.total, self.w, self.at = sweep, w0, np.zeros_like(w0), None, None
        self.step, self.rank, self.places = losses.scalar_step(sweep.loss), 0, {}
        self.dual = DualPass(sweep) if sweep.kind == "dcd" else None
        self.change = self.norm = 0.0

    def deal(self, rows: Rows, order: np.ndarray) -> tuple[np.ndarray, np.ndarray]:
        """(worker, whether its place is in the slice at hand) of these rows in this order, as ``kernels.Dealer`` says it."""
        s, gid = self.sweep, rows.gid[order].astype(np.int64)
        first = _share(gid, s.groups, s.n_blocks)
        nb = _share(gid + 1, s.groups, s.n_blocks) - first
        if s.deal == "dynamic":
            rank = self.rank + np.arange(len(order))
            self.rank += len(order)
            own = rank * s.workers // nb
            place, size = rank - _share(own, s.workers, nb), _share(own + 1, s.workers, nb) - _share(own, s.workers, nb)
            worker = gid * s.workers + own
        else:
            worker = rows.wid[order].astype(np.int64)
            of, own = (s.workers, worker - gid * s.workers) if s.deal == "static" else (s.workers * s.groups, worker)
            nb = nb if s.deal == "static" else s.n_blocks
            size = _share(own + 1, of, nb) - _share(own, of, nb)
            start = np.flatnonzero(np.concatenate(([True], worker[1:] != worker[:-1])))
            place = np.arange(len(worker)) - np.repeat(start, np.diff(np.append(start, len(worker))))
            place[: start[1] if len(start) > 1 else len(worker)] += self.places.get(int(worker[0]), 0)
            self.places = {int(worker[-1]): int(place[-1]) + 1}
        r, p = s.part
        return worker, (size * r // p <= place) & (place < size * (r + 1) // p)

    def over(self, rows: Rows, order: np.ndarray) -> None:
        """Step the rows in this order."""
        if not len(order):
            return
        worker, inside = self.deal(rows, order)
        cut = np.flatnonzero((worker[1:] != worker[:-1]) | (inside[1:] != inside[:-1])) + 1
        for lo, hi in zip([0, *cut.tolist()], [*cut.tolist(), len(order)], strict=True):
            if not inside[lo]:
                continue
            if worker[lo] != self.at:
                self.close()
                self.w, self.at = self.w0.copy(), worker[lo]
            if self.dual:
                self.dual(rows, rows.drawn(order[lo:hi], self.sweep.seed), self.w)
            else:
                step_examples(self.sweep, rows, rows.examples(order[lo:hi], self.sweep), self.w, self.step)
        moved = self.sweep.gamma * (rows.alpha - rows.old)
        rows.alpha = rows.old + moved
        self.change, self.norm = self.change + float(moved @ moved), self.norm + float(rows.alpha @ rows.alpha)

    def close(self) -> None:
        if self.w is not None:
            self.total += (self.w - self.w0) / self.sweep.sigma
            self.w = None

    def end(self, slot: int, gid: int) -> tuple:
        self.close()
        return (0, slot, gid, -1, self.total, self.change, self.norm, *(self.dual.extremes if self.dual else (0.0, 0.0)))


def coordinate_batches(sweep: Sweep, w0: np.ndarray, batches: Iterator) -> Iterator:
    """``kernels.coordinate_sweep`` over Arrow batches: record batches of kind 1, then the group's row of kind 0."""
    run, slot, gid = Pass(sweep, w0), 0, -1
    for batch in batches:
        if not batch.num_rows:
            continue
        rows = Rows.of(batch)
        slot, gid = int(rows.slot[-1]), int(rows.gid[-1])
        run.over(rows, np.arange(len(rows.bid)))
        yield from alpha_batches(rows)
    yield run.end(slot, gid)


class Race:
    """Lock-free rounds with lost updates; see ``kernels.lossy_sweep``. What a round adds to w, and what each node sees of it, is a sum of
    changes of examples that the pattern of writes alone picks, so many rounds are solved together as a chunk's steps are."""

    def __init__(self, sweep: Sweep, w0: np.ndarray):
        self.sweep, self.w0, self.w = sweep, w0, w0.copy()
        self.nodes = max(1, min(sweep.nodes, sweep.threads))
        self.period = sweep.staleness if self.nodes > 1 else 1  # rounds between two looks at all writes
        self.done = self.collisions = self.lost = 0
        self.change = self.norm = 0.0

    def over(self, rows: Rows, take: np.ndarray, last: bool) -> int:
        """Run the rounds of these examples, but for a look that isn't full unless it is the last one; returns how many were used."""
        unit = self.sweep.threads * self.period
        size = max(1, min(chunk_size(self.sweep, rows.largest, self.sweep.threads) or LEAST, most(rows, len(self.w), MOST_WIDE_RACE)) // unit) * unit
        use = len(take) if last else len(take) // unit * unit
        for lo in range(0, use, size):
            self.chunk(rows, take[lo : min(use, lo + size)])
        return use

    def chunk(self, rows: Rows, take: np.ndarray) -> None:
        s, m, d = self.sweep, len(take), len(self.w)
        threads, nodes, period, scale = s.threads, self.nodes, self.period, 1.0 / (s.lam * s.n)
        full = -(-m // (threads * period)) * period  # rounds, with empty places at the end
        x = np.zeros((full * threads, d))
        x[:m] = rows.dense(take, d)
        y, a, q = np.ones(len(x)), np.zeros(len(x)), np.zeros(len(x))
        y[:m], a[:m], q[:m] = rows.y[take], rows.alpha[take], rows.q[take]
        written = (x != 0).reshape(full, nodes, threads // nodes, d)
        seat = np.arange(threads)
        rank = np.broadcast_to(seat, (full, threads))
        rounds = -(-m // threads)
        if nodes > 1:  # no node is always the last to write
            size = np.full(full, threads)
            size[rounds - 1] = m - (rounds - 1) * threads
            rank = (seat - ((self.done + np.arange(full)) % size)[:, None]) % size[:, None]
        ranked = np.where(written, rank.astype(np.int16).reshape(full, nodes, -1, 1), np.int16(-1))
        at = ranked.argmax(axis=2)  # a node's last writer of each column
        place = at + (np.arange(full)[:, None] * threads + np.arange(nodes) * (threads // nodes))[:, :, None]
        best = np.take_along_axis(ranked, at[:, :, None], axis=2)[:, :, 0]
        kept = np.where(best >= 0, x[place, np.arange(d)], 0.0) * scale
        winner, some = best.argmax(axis=1), best.max(axis=1) >= 0
        g, j, c = full // period, np.arange(period), np.arange(d)
        seen = x.reshape(g, period, nodes, threads // nodes, d)
        if nodes == 1:

            def views(delta: np.ndarray) -> tuple:
                moves = delta[place[:, 0]] * kept[:, 0]
                sums = np.cumsum(moves, axis=0)
                return self.w + (sums - moves).reshape(g, 1, 1, d), moves, sums[-1]
        else:
            there = some.reshape(g, period, d)
            last = period - 1 - there[:, ::-1].argmax(axis=1)  # the last round of a look that writes a column
            who, written_at_all = np.take_along_axis(winner.reshape(g, period, d), last[:, None], axis=1)[:, 0], there.any(axis=1)

            def views(delta: np.ndarray) -> tuple:
                moves = (delta[place] * kept).reshape(g, period, nodes, d)
                sums = np.cumsum(moves, axis=1)
                gain = np.where(written_at_all, sums[np.arange(g)[:, None], last, who, c], 0.0)
                all_gains = np.cumsum(gain, axis=0)
                start = self.w + (all_gains - gain)
                return start[:, None, None] + (sums - moves), (start, moves), all_gains[-1]

        margins = lambda delta: np.matmul(seen, views(np.zeros(len(q)) if delta is None else delta)[0][..., None]).ravel()
        unit = threads * period
        delta = settle(s.loss, q, y, a, q * scale, margins, SWEEPS if m > unit else 50 * SWEEPS)
        if delta is None:
            if m <= unit:
                raise FloatingPointError("the steps of a round don't settle")
            half = max(1, m // unit // 2) * unit
            self.chunk(rows, take[:half])
            self.chunk(rows, take[half:])
            return
        _, state, gain = views(delta)
        self.collisions += int(written.sum() - some.sum())
        written_changes = int((written.reshape(-1, d)[delta != 0]).sum())
        if nodes == 1:
            self.lost += written_changes - int(np.count_nonzero(state))
        else:
            now, moves = state
            winner, seen_by = winner.reshape(g, period, d), np.repeat(now[:, None], nodes, axis=1)
            now, kept_changes = now.copy(), 0
            for k in j.tolist():
                mine = winner[:, k][:, None]
                base, own = np.take_along_axis(seen_by, mine, axis=1)[:, 0], np.take_along_axis(moves[:, k], mine, axis=1)[:, 0]
                kept_changes += int(np.count_nonzero(own[there[:, k]]))
                self.lost += int(((base != now) & there[:, k]).sum())
                now = np.where(there[:, k], base + own, now)
                seen_by = seen_by + moves[:, k]
            self.lost += written_changes - kept_changes
        rows.alpha[take] = (a + delta)[:m]
        self.w = self.w + gain
        self.done += rounds

    def count(self, rows: Rows, hi: int) -> None:
        """Take the rows' first ``hi`` examples into the sums."""
        new, old = rows.alpha[:hi], rows.old[:hi]
        self.change, self.norm = self.change + float(((new - old) ** 2).sum()), self.norm + float((new**2).sum())

    def end(self, slot: int, gid: int) -> tuple:
        return (0, slot, gid, -1, self.w - self.w0, self.change, self.norm, float(self.collisions), float(self.lost))


class SparseRace(Race):
    """The same over the values that are there. A write counts inside its node and look; a look's gain in a column is what the node that writes
    it last has gathered."""

    def chunk(self, rows: Rows, take: np.ndarray) -> None:
        s, m, d = self.sweep, len(take), len(self.w)
        threads, nodes, period, scale = s.threads, self.nodes, self.period, 1.0 / (s.lam * s.n)
        y, a, q = rows.y[take], rows.alpha[take], rows.q[take]
        row, e = rows.entries(take)
        col, val = rows.idx[e].astype(np.int64), rows.val[e]
        z, there = np.bincount(row, weights=val * self.w[col], minlength=m), val != 0
        row, col, val = row[there], col[there], val[there]
        rounds = -(-m // threads)
        turn, seat = np.divmod(np.arange(m), threads)
        node, size = seat * nodes // threads, np.full(m, threads)
        size[(rounds - 1) * threads :] = m - (rounds - 1) * threads
        rank = (seat - (self.done + turn) % size) % size if nodes > 1 else seat  # no node is always the last to write
        if nodes == 1:
            order = np.argsort(col.astype(np.uint16) if d <= 1 << 16 else col, kind="stable")
        else:  # by column, look, node, round and place in the round
            order = np.argsort(((col * (rounds // period + 1) + (turn // period)[row]) * nodes + node[row]) * (period * threads) + (turn % period * threads + rank)[row], kind="stable")
        row, col, val = row[order], col[order], val[order]
        turn, node, rank = turn[row], node[row], rank[row]
        look, n = turn // period, len(row)

        def starts(*keys: np.ndarray) -> tuple[np.ndarray, np.ndarray]:
            """(first place of each run of equal keys, number of the run of each place)."""
            new = np.ones(n, dtype=bool)
            if n:
                new[1:] = np.logical_or.reduce([k[1:] != k[:-1] for k in keys])
            return np.flatnonzero(new), np.cumsum(new) - 1

        looks, of_look = starts(col, look)
        groups, of_group = (looks, of_look) if nodes == 1 else starts(col, look, node)
        writes, of_write = (looks, of_look) if nodes == 1 else starts(col, look, node, turn)
        last = np.append(writes[1:], n) - 1 if n else writes  # the node's last writer of a column in a round
        moved, kept_row = scale * val[last], row[last]
        group_of = of_group[last]
        first_write = of_write[groups]  # of each group
        columns = np.flatnonzero(np.append(True, col[looks][1:] != col[looks][:-1])) if n else looks  # the first look of each column
        of_column = np.repeat(np.arange(len(columns)), np.diff(np.append(columns, len(looks))))
        if nodes == 1:
            winner = np.arange(len(looks))
        else:  # of each look: the group of its last write
            late = turn[last] * threads + rank[last]
            by = np.lexsort((late, of_look[last]))
            winner = group_of[by[np.append(np.flatnonzero(np.diff(of_look[last][by])), len(by) - 1)]] if n else groups

        def sums(delta: np.ndarray) -> tuple:
            moves = moved * delta[kept_row]
            total = np.cumsum(moves)
            before = total - moves  # of each write
            start = before[first_write]
            gain = (np.append(start[1:], total[-1:]) - start)[winner]
            earlier = np.cumsum(gain) - gain
            earlier -= earlier[columns][of_column]
            return moves, before - start[group_of], gain, earlier

        def margins(delta: np.ndarray | None) -> np.ndarray:
            if delta is None:
                return z
            _, inside, _, earlier = sums(delta)
            return z + np.bincount(row, weights=val * (earlier[of_look] + inside[of_write]), minlength=m)

        unit = threads * period
        delta = settle(s.loss, q, y, a, q * scale, margins, SWEEPS if m > unit else 50 * SWEEPS)
        if delta is None:
            if m <= unit:
                raise FloatingPointError("the steps of a round don't settle")
            half = max(1, m // unit // 2) * unit
            self.chunk(rows, take[:half])
            self.chunk(rows, take[half:])
            return
        if n:
            moves, inside, gain, _ = sums(delta)
            written = int(np.count_nonzero(delta[row]))
            if nodes == 1:
                self.collisions += n - len(looks)
                self.lost += written - int(np.count_nonzero(moves))
            else:
                by = np.lexsort((rank[last], turn[last], of_look[last]))  # by column, look and round
                cell = np.stack((of_look[last][by], turn[last][by]))
                new = np.append(True, (cell[:, 1:] != cell[:, :-1]).any(axis=0))
                wins = by[np.append(np.flatnonzero(new)[1:], len(by)) - 1]  # the last write of each column in a round
                self.collisions += n - len(wins)
                self.lost += written - int(np.count_nonzero(moves[wins]))
                seen, after = inside[wins], inside[wins] + moves[wins]
                same_look = of_look[last][wins][1:] == of_look[last][wins][:-1]
                same_node = group_of[wins][1:] == group_of[wins][:-1]
                self.lost += int((same_look & ~same_node & (np.abs(seen[1:] - after[:-1]) > SETTLED * np.abs(moved).max())).sum())
            np.add.at(self.w, col[looks], gain)
        rows.alpha[take] = a + delta
        self.done += rounds


def race_for(sweep: Sweep, rows: Rows, d: int) -> type[Race] | None:
    """The form of lock-free rounds with lost updates that suits these rows; None if they go one by one."""
    if sweep.kind != "lossy" or sweep.threads < 2 or not sweep.lost or sweep.loss_rate < 1.0 or not chunk_size(sweep, rows.largest, sweep.threads):
        return None
    if rows.idx is not None:
        return SparseRace
    return Race if d <= RACE_COLUMNS and sweep.threads % max(1, min(sweep.nodes, sweep.threads)) == 0 else None


def race_batches(sweep: Sweep, w0: np.ndarray, batches: Iterator, kind: type[Race]) -> Iterator:
    """``kernels.lossy_sweep`` over Arrow batches: record batches of kind 1, then the group's row of kind 0."""
    race, held, start = kind(sweep, w0), None, 0
    for batch in batches:
        if not batch.num_rows:
            continue
        rows = Rows.of(batch)
        if held is not None:
            rows = Rows.join([held, rows])
        done = start + race.over(rows, rows.examples(np.arange(len(rows.bid)), sweep)[start:], False)
        k = int(np.searchsorted(rows.at, done, side="right")) - 1  # rows whose examples are all done
        race.count(rows, int(rows.at[k]))
        yield from alpha_batches(rows, k)
        held, start = rows.tail(k), done - int(rows.at[k])
    slot, gid = 0, -1
    if held is not None:
        slot, gid = int(rows.slot[-1]), int(rows.gid[-1])
        if len(held.bid):
            race.over(held, held.examples(np.arange(len(held.bid)), sweep)[start:], True)
            race.count(held, len(held.y))
            yield from alpha_batches(held)
    yield race.end(slot, gid)
