"""What one task does in an epoch: a pass over its group's rows, streamed in the order in which they were drawn.

Rows come sorted by the epoch's key (dynamic dealing) or by worker and key (static, global). Under dynamic dealing the
rank of a row in its group is the number of rows that came before it, and worker k of m gets the ranks from k nb / m on: a run
of neighbours, so one replica of w = v / (lam n) is held at a time and no rank is computed by Spark. With one worker this
is the plain sequential solver. Memory: one replica, the group's sum of changes and one row. A kernel is a function of
its input alone, so retried tasks give the same rows. Numbers are read as views of the Arrow buffers.
"""

from __future__ import annotations

from collections.abc import Callable, Iterator
from dataclasses import dataclass, replace
from functools import cached_property
from itertools import chain

import numpy as np

from coordloom.operators import losses, permute

OUT = "kind int, slot int, gid int, bid long, vec array<double>, s0 double, s1 double, s2 double, s3 double"
#: Examples that are stepped against one product with w; their influence on each other goes through their Gram matrix.
CHUNK = 64
#: Cells of a chunk's dense form for sparse examples; above it they are stepped one by one.
CHUNK_CELLS = 1 << 16


@dataclass(frozen=True)
class Sweep:
    """Parameters of a pass; ``kind`` is coordinate, dcd, lossy, sag or sgd."""

    loss: str
    lam: float
    n: int
    d: int
    workers: int  # of the group
    sigma: float = 1.0
    gamma: float = 1.0
    shared_updates: bool = True
    kind: str = "coordinate"
    threads: int = 1
    lost: bool = True
    loss_rate: float = 1.0
    staleness: int = 1
    nodes: int = 1
    shrink: tuple[float, float] | None = None
    rate: float = 0.0
    part: tuple[int, int] = (0, 1)  # slice r of p of each worker's list
    deal: str = "dynamic"
    n_blocks: int = 1
    groups: int = 1
    unit: int = 0
    seed: int = 0  # of the order inside rows
    ordered: bool = False  # rows keep their own order inside


class Block:
    __slots__ = ("alpha", "bid", "gid", "idx", "indptr", "old", "slot", "val", "wid", "y")

    def order(self, sweep: Sweep) -> Iterator[np.ndarray]:
        """The row's examples: its buckets of ``unit`` in drawn order, in chunks of whole buckets or parts of one."""
        m, unit = len(self.y), sweep.unit or len(self.y)
        if unit >= m or sweep.ordered:
            for lo in range(0, m, CHUNK):
                yield np.arange(lo, min(m, lo + CHUNK))
            return
        drawn = np.random.default_rng((sweep.seed, self.bid)).permutation(-(-m // unit))
        places = (drawn[:, None] * unit + np.arange(unit)).ravel()
        places = places[places < m]
        for lo in range(0, m, CHUNK):
            yield places[lo : lo + CHUNK]


def lists(column) -> tuple[np.ndarray, np.ndarray]:
    """(offsets, flat values) of an Arrow list column, without copies."""
    return np.asarray(column.offsets), np.asarray(column.values)


def blocks_of(batches: Iterator) -> Iterator[Block]:
    for batch in batches:
        if hasattr(batch, "blocks"):  # rows as flat arrays
            yield from batch.blocks()
            continue
        names = batch.schema.names
        column = {c: batch.column(c) for c in names}
        gid, bid = np.asarray(column["gid"]), np.asarray(column["bid"])
        slot = np.asarray(column["slot"])
        wid = np.asarray(column["wid"]) if "wid" in column else None
        dense, fresh = bool(column["idx"].null_count), np.asarray(column["alpha"].is_null())
        (y_at, y), (p_at, p), (v_at, v), (a_at, a) = (lists(column[c]) for c in ("y", "indptr", "val", "alpha"))
        i_at, i = (None, None) if dense else lists(column["idx"])
        for k in range(batch.num_rows):
            b = Block()
            b.gid, b.bid, b.slot, b.wid = int(gid[k]), int(bid[k]), int(slot[k]), -1 if wid is None else int(wid[k])
            b.y, b.indptr, b.val = y[y_at[k] : y_at[k + 1]], p[p_at[k] : p_at[k + 1]], v[v_at[k] : v_at[k + 1]]
            b.idx = None if dense else i[i_at[k] : i_at[k + 1]]
            b.old = np.zeros(len(b.y)) if fresh[k] else np.array(a[a_at[k] : a_at[k + 1]])
            b.alpha = b.old.copy()
            yield b


def examples_of(batch) -> tuple[np.ndarray, np.ndarray, np.ndarray, np.ndarray]:
    """(example of each value, column of each value, value, y) of all rows of a batch at once."""
    (p_at, p), (v_at, v), (y_at, y) = (lists(batch.column(c)) for c in ("indptr", "val", "y"))
    p, v, y = p[p_at[0] : p_at[-1]], v[v_at[0] : v_at[-1]], y[y_at[0] : y_at[-1]]
    sizes = np.delete(np.diff(p), (p_at[1:-1] - p_at[0] - 1)) if len(p) else np.empty(0, np.int64)
    row = np.repeat(np.arange(len(sizes)), sizes)
    if batch.column("idx").null_count:
        idx = np.arange(len(v)) - np.repeat(np.cumsum(sizes) - sizes, sizes)
    else:
        i_at, i = lists(batch.column("idx"))
        idx = i[i_at[0] : i_at[-1]]
    return row, idx, v, y


def alphas_of(batch, n: int) -> np.ndarray:
    """alpha of all examples of a batch, 0 where a row has none yet."""
    column = batch.column("alpha")
    if not column.null_count:
        at, a = lists(column)
        return a[at[0] : at[-1]]
    y_at, _ = lists(batch.column("y"))
    out, at = np.zeros(n), np.asarray(column.offsets)
    flat = np.asarray(column.values)
    for k in np.flatnonzero(~np.asarray(column.is_null())):
        out[y_at[k] - y_at[0] : y_at[k + 1] - y_at[0]] = flat[at[k] : at[k + 1]]
    return out


def _share(k: int, of: int, n: int) -> int:
    """First of n places that belongs to part k of ``of`` (and later parts)."""
    return -(-k * n // of)


class Dealer:
    """Says which worker gets the next row, and whether its place is in the slice at hand."""

    def __init__(self, sweep: Sweep):
        self.sweep, self.rank, self.places = sweep, 0, {}

    def __call__(self, b: Block) -> tuple[int, bool]:
        s = self.sweep
        if s.deal == "dynamic":
            first = _share(b.gid, s.groups, s.n_blocks)
            nb = _share(b.gid + 1, s.groups, s.n_blocks) - first
            own = self.rank * s.workers // nb
            place, size = self.rank - _share(own, s.workers, nb), _share(own + 1, s.workers, nb) - _share(own, s.workers, nb)
            self.rank += 1
            worker = b.gid * s.workers + own
        else:
            worker = b.wid
            if s.deal == "static":
                first = _share(b.gid, s.groups, s.n_blocks)
                nb, of, own = _share(b.gid + 1, s.groups, s.n_blocks) - first, s.workers, worker - b.gid * s.workers
            else:
                nb, of, own = s.n_blocks, s.workers * s.groups, worker
            size = _share(own + 1, of, nb) - _share(own, of, nb)
            place = self.places.get(worker, 0)
            self.places = {worker: place + 1}
        r, p = s.part
        return worker, size * r // p <= place < size * (r + 1) // p


def step_block(sweep: Sweep, b: Block, w: np.ndarray, step: Callable) -> None:
    """Exact steps on the row's examples; changes ``b.alpha`` and the replica ``w``."""
    scale = sweep.sigma / (sweep.lam * sweep.n)
    for take in b.order(sweep):
        inside = None
        if b.idx is None:
            x = b.val.reshape(len(b.y), -1)[take]
        elif len(take) == 1:
            _one_by_one(sweep, b, w, step, take, scale)
            continue
        else:
            starts, sizes = b.indptr[take], b.indptr[take + 1] - b.indptr[take]
            flat = np.repeat(starts - np.cumsum(sizes) + sizes, sizes) + np.arange(int(sizes.sum()))
            inside, where = np.unique(b.idx[flat], return_inverse=True)
            if len(take) * len(inside) > CHUNK_CELLS:
                _one_by_one(sweep, b, w, step, take, scale)
                continue
            x = np.zeros((len(take), len(inside)))
            x[np.repeat(np.arange(len(take)), sizes), where] = b.val[flat]
        z = x @ (w if inside is None else w[inside])
        if len(take) == 1:
            k = take[0]
            q = float(x[0] @ x[0])
            delta = step(float(z[0]), q, float(b.y[k]), float(b.alpha[k]), q * scale)
            b.alpha[k] += delta
            if sweep.shared_updates:
                w += (scale * delta) * x[0]
            continue
        gram = x @ x.T
        q, y, a = gram.diagonal().tolist(), b.y[take].tolist(), b.alpha[take].tolist()
        moved = gram * scale
        changes = np.empty(len(take))
        for k in range(len(take)):
            delta = step(float(z[k]), q[k], y[k], a[k], q[k] * scale)
            changes[k] = delta
            if sweep.shared_updates:
                z += delta * moved[k]
        b.alpha[take] += changes
        if sweep.shared_updates:
            move = (scale * changes) @ x
            if inside is None:
                w += move
            else:
                w[inside] += move


def in_order(sweep: Sweep, b: Block) -> bool:
    """Whether the row's examples are taken as they lie."""
    return sweep.ordered or not 0 < sweep.unit < len(b.y)


def joined(rows: list[Block]) -> Block:
    """Rows that are stepped one after another as one row; its alpha is a copy."""
    out = Block()
    out.bid, out.gid, out.slot, out.wid = rows[0].bid, rows[0].gid, rows[0].slot, rows[0].wid
    out.y, out.val, out.old, out.alpha = (np.concatenate([getattr(b, c) for b in rows]) for c in ("y", "val", "old", "alpha"))
    out.idx = None if rows[0].idx is None else np.concatenate([b.idx for b in rows])
    sizes = np.concatenate([b.indptr[1:] - b.indptr[:-1] for b in rows])
    out.indptr = np.concatenate(([0], np.cumsum(sizes)))
    return out


def step_rows(sweep: Sweep, rows: list[Block], w: np.ndarray, step: Callable) -> None:
    """``step_block`` over short rows that are taken as they lie: the same steps, with one product and one Gram matrix for all of them."""
    if len(rows) == 1:
        step_block(sweep, rows[0], w, step)
        return
    whole = joined(rows)
    step_block(sweep if sweep.ordered else replace(sweep, ordered=True), whole, w, step)
    lo = 0
    for b in rows:
        b.alpha[:] = whole.alpha[lo : lo + len(b.y)]
        lo += len(b.y)


def _one_by_one(sweep: Sweep, b: Block, w: np.ndarray, step: Callable, take: np.ndarray, scale: float) -> None:
    for k in take.tolist():
        c, x = b.idx[b.indptr[k] : b.indptr[k + 1]], b.val[b.indptr[k] : b.indptr[k + 1]]
        q = float(x @ x)
        delta = step(float(w[c] @ x), q, float(b.y[k]), float(b.alpha[k]), q * scale)
        b.alpha[k] += delta
        if sweep.shared_updates:
            w[c] += (scale * delta) * x


def _row(b: Block, new: np.ndarray) -> tuple:
    return (1, b.slot, b.gid, b.bid, new, 0.0, 0.0, 0.0, 0.0)


def coordinate_sweep(sweep: Sweep, w0: np.ndarray, blocks: Iterator[Block]) -> Iterator[tuple]:
    """All workers of a group, one after another, each on a replica of its own; their changes are added up for the group."""
    step, dealer = losses.scalar_step(sweep.loss), Dealer(sweep)
    pass_over = dual_pass(sweep) if sweep.kind == "dcd" else None
    total, w, at, change, norm, slot, gid = np.zeros_like(w0), None, None, 0.0, 0.0, 0, -1
    waiting: list[Block] = []  # neighbours of one worker, to be stepped together
    examples = 0

    def finish(rows: list[Block]) -> Iterator[tuple]:
        nonlocal change, norm
        old, alpha = (rows[0].old, rows[0].alpha) if len(rows) == 1 else (np.concatenate([b.old for b in rows]), np.concatenate([b.alpha for b in rows]))
        moved = sweep.gamma * (alpha - old)
        new = old + moved
        change, norm = change + float(moved @ moved), norm + float(new @ new)
        lo = 0
        for b in rows:
            yield _row(b, new[lo : lo + len(b.y)])
            lo += len(b.y)

    def flush() -> Iterator[tuple]:
        nonlocal examples
        step_rows(sweep, waiting, w, step)
        yield from finish(waiting)
        waiting.clear()
        examples = 0

    for b in blocks:
        slot, gid = b.slot, b.gid
        worker, inside = dealer(b)
        if waiting and (not inside or worker != at or examples + len(b.y) > CHUNK):
            yield from flush()
        if inside and worker != at:
            if w is not None:
                total += (w - w0) / sweep.sigma
            w, at = w0.copy(), worker
        if inside and not pass_over and len(b.y) < CHUNK and in_order(sweep, b):
            waiting.append(b)
            examples += len(b.y)
            continue
        if inside:
            if pass_over:
                pass_over(b, w)
            else:
                step_block(sweep, b, w, step)
        yield from finish([b])
    if waiting:
        yield from flush()
    if w is not None:
        total += (w - w0) / sweep.sigma
    extremes = pass_over.extremes if pass_over else (0.0, 0.0)
    yield (0, slot, gid, -1, total, change, norm, *extremes)


class dual_pass:  # noqa: N801  a callable with state
    """The dual descent of the libraries: examples permuted one by one, inner problems solved to a tolerance that follows the
    worst gradient of the last pass, examples that were near their optimum left out until the others are there too.

    Logistic: Newton on b itself, towards the nearer end of (0, 1), a tenth of the way to an end that a step would cross.
    Bounded losses: an example at a bound whose gradient points outwards beyond the last pass's extremes is left out. ``shrink`` is
    (threshold, -) for logistic and (highest, lowest projected gradient) for bounded losses; None leaves nothing out.
    """

    INNER = 8

    def __init__(self, sweep: Sweep):
        self.sweep, self.step = sweep, losses.scalar_step(sweep.loss)
        self.extremes = (0.0, 0.0) if sweep.loss == "logistic" else (-np.inf, np.inf)

    def __call__(self, b: Block, w: np.ndarray, places: np.ndarray | None = None) -> None:
        s = self.sweep
        scale = s.sigma / (s.lam * s.n)
        if places is None:
            places = permute.inside_rows(np.array([b.bid]), np.array([len(b.y)]), s.seed)
        for k in places.tolist():
            x = b.val[b.indptr[k] : b.indptr[k + 1]]
            c = slice(None) if b.idx is None else b.idx[b.indptr[k] : b.indptr[k + 1]]
            z, q, y, a = float(w[c] @ x), float(x @ x), float(b.y[k]), float(b.alpha[k])
            delta = self._logistic(z, q * scale, y, a) if s.loss == "logistic" else self._bounded(z, q, y, a, q * scale)
            if delta:
                b.alpha[k] += delta
                w[c] += (scale * delta) * x

    def _logistic(self, z: float, s: float, y: float, a: float) -> float:
        old = y * a
        b = min(max(old, 1e-8), 1.0 - 1e-8)
        slope = y * z + s * (b - old) + np.log(b / (1.0 - b))
        self.extremes = (max(self.extremes[0], abs(slope)), 0.0)
        threshold = self.sweep.shrink[0] if self.sweep.shrink else 0.0
        if abs(slope) <= threshold:
            return 0.0
        for _ in range(self.INNER):
            new = b - slope / (s + 1.0 / (b * (1.0 - b)))
            b = 0.1 * b if new <= 0.0 else 1.0 - 0.1 * (1.0 - b) if new >= 1.0 else new
            slope = y * z + s * (b - old) + np.log(b / (1.0 - b))
            if abs(slope) <= max(1e-10, 0.1 * threshold):
                break
        return float(y * (b - old))

    def _bounded(self, z: float, q: float, y: float, a: float, s: float) -> float:
        if self.sweep.shrink is not None and self.sweep.loss in ("hinge", "smooth_hinge"):
            b, g = y * a, y * z - 1.0
            high, low = self.sweep.shrink
            if (b <= 1e-12 and g > high) or (b >= 1 - 1e-12 and g < low):
                return 0.0
            projected = min(g, 0.0) if b <= 1e-12 else max(g, 0.0) if b >= 1 - 1e-12 else g
            self.extremes = (max(self.extremes[0], projected), min(self.extremes[1], projected))
        return self.step(z, q, y, a, s)


def lossy_sweep(sweep: Sweep, w0: np.ndarray, blocks: Iterator[Block]) -> Iterator[tuple]:
    """Rounds of ``threads`` examples. Thread r runs on node r nodes / threads; a node sees the writes of its own threads after the round and
    all others' only every ``staleness`` rounds.

    Lost mode: a thread writes back what its node sees plus its change, so of the writers of a component in a round the last one
    wins, and what other nodes wrote since the last refresh is overwritten. ``loss_rate`` below 1 loses an overwritten
    change with that chance, drawn by a hash. Otherwise reads are stale and no change is lost."""
    scale, w, done, collisions, lost = 1.0 / (sweep.lam * sweep.n), w0.copy(), 0, 0, 0
    threads, nodes = sweep.threads, max(1, min(sweep.nodes, sweep.threads))
    node_of = [r * nodes // threads for r in range(threads)]
    views = np.repeat(w[None, :], nodes, axis=0)
    step, plain = losses.scalar_step(sweep.loss), sweep.loss_rate >= 1.0 or not sweep.lost
    waiting: list[tuple[Block, int]] = []

    def together(turn: int) -> tuple:
        """The round's writes, in the order of writing: (columns, changes, thread of each, threads in order)."""
        cols, moves, owner, seats = [], [], [], []
        for r, (b, k) in [*enumerate(waiting)][turn:] + [*enumerate(waiting)][:turn]:
            x = b.val[b.indptr[k] : b.indptr[k + 1]]
            c = np.arange(len(x)) if b.idx is None else b.idx[b.indptr[k] : b.indptr[k + 1]]
            view = views[node_of[r]]
            q = float(x @ x)
            delta = step(float(view[c] @ x), q, float(b.y[k]), float(b.alpha[k]), q * scale)
            b.alpha[k] += delta
            here = x != 0
            cols.append(c[here])
            moves.append((scale * delta) * x[here])
            owner.append(np.full(int(here.sum()), r))
            seats.append(r)
        return np.concatenate(cols), np.concatenate(moves), np.concatenate(owner), seats, cols, moves

    def run_dense() -> None:
        """``run`` for dense examples: the same writes as whole columns."""
        nonlocal done, collisions, lost
        turn = done % len(waiting) if nodes > 1 else 0
        order = waiting[turn:] + waiting[:turn]
        x = np.stack([b.val[b.indptr[k] : b.indptr[k + 1]] for b, k in order])
        if nodes > 1:
            if done % sweep.staleness == 0:
                views[:] = w
            node = np.asarray(node_of)[np.roll(np.arange(len(waiting)), -turn)]
            z = np.einsum("ij,ij->i", x, views[node]).tolist()
        else:
            z = (x @ w).tolist()
        q = np.einsum("ij,ij->i", x, x).tolist()
        deltas = np.empty(len(order))
        for r, (b, k) in enumerate(order):
            deltas[r] = delta = step(z[r], q[r], float(b.y[k]), float(b.alpha[k]), q[r] * scale)
            b.alpha[k] += delta
        move, written = (scale * deltas)[:, None] * x, x != 0
        writers = written.sum(axis=0)
        collisions += int(writers.sum() - np.count_nonzero(writers))
        column = np.arange(x.shape[1])
        if sweep.lost:
            last = len(order) - 1 - np.argmax(written[::-1], axis=0)
            kept = move[last, column]  # 0 where nobody writes
            lost += int(np.count_nonzero(move) - np.count_nonzero(kept))
            if nodes > 1:
                base = views[node[last], column]
                stale = (base != w) & (writers > 0)
                lost += int(stale.sum())
                w[stale] = base[stale]
            np.add(w, kept, out=w)
        else:
            np.add(w, move.sum(axis=0), out=w)
        if nodes > 1:
            for g in np.unique(node).tolist():
                mine = np.flatnonzero(node == g)
                own = written[mine]
                views[g] += move[mine[len(mine) - 1 - np.argmax(own[::-1], axis=0)], column]  # 0 where the node writes nothing
        done += 1
        waiting.clear()

    def run() -> None:
        nonlocal done, collisions, lost
        if plain and waiting[0][0].idx is None:
            run_dense()
            return
        if nodes == 1 or done % sweep.staleness == 0:
            views[:] = w
        col, move, who, seats, cols, moves = together(done % len(waiting) if nodes > 1 else 0)  # no node is always the last to write
        back, first = np.unique(col[::-1], return_index=True)
        last = len(col) - 1 - first  # the last writer of each component
        collisions += len(col) - len(back)
        if not sweep.lost:
            np.add.at(w, col, move)
        else:
            node = np.asarray(node_of)[who]
            beaten = np.ones(len(col), dtype=bool)
            beaten[last] = False
            stale = views[node[last], back] != w[back]
            kept = np.zeros(len(col), dtype=bool)
            if sweep.loss_rate < 1.0:
                draw = ((col.astype(np.int64) * 2654435761 + done * 40503 + who * 9176) % 100003) / 100003.0
                kept = beaten & (draw >= sweep.loss_rate)
            lost += int((beaten & ~kept & (move != 0)).sum()) + int(stale.sum())
            w[back] = views[node[last], back] + move[last]
            np.add.at(w, col[kept], move[kept])
        if nodes > 1:
            seen = views.copy()
            for r, c, own in zip(seats, cols, moves, strict=True):
                views[node_of[r]][c] = seen[node_of[r]][c] + own
        done += 1
        waiting.clear()

    change = norm = 0.0
    held: list[Block] = []
    slot, gid = 0, -1

    def out(b: Block) -> tuple:
        nonlocal change, norm
        change, norm = change + float(((b.alpha - b.old) ** 2).sum()), norm + float((b.alpha**2).sum())
        return _row(b, b.alpha)

    for b in blocks:
        slot, gid = b.slot, b.gid
        if threads == 1:  # nobody to race with
            step_block(sweep, b, w, step)
            yield out(b)
            continue
        held.append(b)
        for take in b.order(sweep):
            for k in take.tolist():
                waiting.append((b, k))
                if len(waiting) == threads:
                    run()
        while held and not any(x is held[0] for x, _ in waiting):  # a row whose examples are all done goes out
            yield out(held.pop(0))
    if waiting:
        run()
    for b in held:
        yield out(b)
    yield (0, slot, gid, -1, w - w0, change, norm, float(collisions), float(lost))


def _each(sweep: Sweep, b: Block) -> Iterator[tuple]:
    for take in b.order(sweep):
        for k in take.tolist():
            x = b.val[b.indptr[k] : b.indptr[k + 1]]
            yield k, slice(None) if b.idx is None else b.idx[b.indptr[k] : b.indptr[k + 1]], x


def sag_sweep(sweep: Sweep, w0: np.ndarray, average: np.ndarray, blocks: Iterator[Block]) -> Iterator[tuple]:
    """Stochastic average gradient: one scalar slope per example (kept where alpha is kept) and their average direction."""
    w, g, slot = w0.copy(), average.copy(), 0
    for b in blocks:
        slot = b.slot
        for k, c, x in _each(sweep, b):
            new = float(losses.slope(sweep.loss, float(w[c] @ x), b.y[k]))
            g[c] += (new - b.alpha[k]) / sweep.n * x
            b.alpha[k] = new
            w -= sweep.rate * (g + sweep.lam * w)
        yield _row(b, b.alpha)
    yield (0, slot, -1, -1, w - w0, 0.0, 0.0, 0.0, 0.0)
    yield (2, slot, -1, -1, g - average, 0.0, 0.0, 0.0, 0.0)


def sgd_sweep(sweep: Sweep, w0: np.ndarray, blocks: Iterator[Block]) -> Iterator[tuple]:
    """One online pass with a falling rate."""
    w, t = w0.copy(), 0
    for b in blocks:
        for k, c, x in _each(sweep, b):
            rate = sweep.rate / (1 + sweep.rate * sweep.lam * t)
            slope = float(losses.slope(sweep.loss, float(w[c] @ x), b.y[k]))
            w *= 1 - rate * sweep.lam
            w[c] -= rate * slope * x
            t += 1
    yield (0, 0, -1, -1, w - w0, 0.0, 0.0, 0.0, 0.0)


def run_sweep(sweep: Sweep, w0: np.ndarray, extra: np.ndarray | None, batches: Iterator) -> Iterator:
    """All output of one task, as rows or record batches: kind 1 the rows' new alpha, kind 0 the group's change of w and its sums, kind 2 further state."""
    from coordloom.operators import flat

    if sweep.kind in ("coordinate", "dcd") or sweep.kind == "lossy" and sweep.threads == 1:
        yield from flat.coordinate_batches(sweep, w0, batches)
        return
    if sweep.kind in ("sag", "sgd"):
        yield from flat.gradient_batches(sweep, w0, extra, batches)
        return
    batches = (b for b in batches if b.num_rows)
    first = next(batches, None)
    batches = chain([] if first is None else [first], batches)
    race = None if first is None else flat.race_for(sweep, flat.Rows.of(first), len(w0))
    yield from lossy_sweep(sweep, w0, blocks_of(batches)) if race is None else flat.race_batches(sweep, w0, batches, race)


# Whole runs inside one task, for groups that fit in memory


def by_columns(columns: list[np.ndarray]) -> np.ndarray:
    """The order by these columns, the leading one first; the others are looked at only where it has ties."""
    order = np.argsort(columns[0])
    leading = columns[0][order]
    return order if (leading[1:] != leading[:-1]).all() else np.lexsort(columns[::-1])


class Resident:
    """All rows of a group, kept between passes; ``keys`` gives the sort keys of the next one. A run is one kind of sweep, and either
    takes the rows as flat arrays (``flat``) or as blocks. ``n`` and ``cells`` say how many examples and values come; slabs are taken apart into
    rows of ``bucket`` examples."""

    def __init__(self, batches: Iterator, n: int = 0, cells: int = 0, bucket: int = 1, slab: int = 1):
        from coordloom.operators import flat

        parts = (flat.Rows.of(b) for b in batches if b.num_rows)
        self.rows = self.whole = flat.Rows.gather(parts, n, cells)
        self.slot = int(self.rows.slot[-1]) if self.rows else 0
        if slab > 1 and self.rows:
            self.rows = self.whole.apart(bucket, slab)

    @cached_property
    def blocks(self) -> list[Block]:
        """The rows as blocks, views of the flat arrays."""
        return [] if self.rows is None else list(self.rows.blocks())

    def order(self, sweep: Sweep, keys: Callable[[np.ndarray], tuple]) -> np.ndarray:
        """The rows' numbers in the order of the pass; ``keys`` gives columns, the leading one first."""
        bids = self.rows.bid
        order = by_columns([*keys(bids), bids])
        if sweep.deal == "static":
            gid = self.rows.gid.astype(np.int64)
            first = _share(gid, sweep.groups, sweep.n_blocks)
            self.rows.wid = gid * sweep.workers + (bids - first) * sweep.workers // (_share(gid + 1, sweep.groups, sweep.n_blocks) - first)
            wid = self.rows.wid[order] - self.rows.wid.min()
            order = order[np.argsort(wid.astype(np.uint16) if wid.max() < 1 << 16 else wid, kind="stable")]
        return order

    def run(self, sweep: Sweep, keys: Callable[[np.ndarray], tuple], w: np.ndarray, extra: np.ndarray | None = None) -> list[tuple]:
        """One pass: the rows of all kinds but 1, whose alphas stay here."""
        from coordloom.operators import flat

        if self.rows is None:
            rows = sag_sweep(sweep, w, extra, iter(())) if sweep.kind == "sag" else coordinate_sweep(sweep, w, iter(()))
            return list(rows)
        rows, order = self.rows, self.order(sweep, keys)
        if sweep.kind == "sag":
            run = flat.Gradients(sweep, w, extra)
            run.over(rows, rows.examples(order, sweep))
            rows.old = rows.alpha.copy()
            return run.end(self.slot)
        if sweep.kind in ("coordinate", "dcd") or sweep.kind == "lossy" and sweep.threads == 1:
            run = flat.Pass(sweep, w)
            run.over(rows, order)
        elif race := flat.race_for(sweep, rows, len(w)):
            run = race(sweep, w)
            run.over(rows, rows.examples(order, sweep), True)
            run.count(rows, len(rows.y))
        else:
            return self._run_blocks(sweep, order, w, extra)
        rows.old = rows.alpha.copy()
        return [run.end(self.slot, int(rows.gid[-1]))]

    def _run_blocks(self, sweep: Sweep, order: np.ndarray, w: np.ndarray, extra: np.ndarray | None) -> list[tuple]:
        at, out = dict(zip(self.rows.bid.tolist(), range(len(order)), strict=True)), []
        if self.rows.wid is not None:
            for b, wid in zip(self.blocks, self.rows.wid.tolist(), strict=True):
                b.wid = wid
        blocks = (self.blocks[k] for k in order.tolist())
        new = {}
        for row in lossy_sweep(sweep, w, blocks) if sweep.kind == "lossy" else sag_sweep(sweep, w, extra, blocks) if sweep.kind == "sag" else coordinate_sweep(sweep, w, blocks):
            if row[0] == 1:
                new[row[3]] = row[4]
            else:
                out.append(row)
        rows = self.rows
        for bid, alpha in new.items():
            k = at[bid]
            b = self.blocks[k]
            b.old = np.array(alpha)
            b.alpha = b.old.copy()
            rows.alpha[rows.at[k] : rows.at[k + 1]] = b.old
        return out

    def alphas(self) -> Iterator:
        """The rows' alphas as record batches."""
        from coordloom.operators import flat

        if self.rows is not None:
            self.whole.alpha = self.rows.alpha
            yield from flat.alpha_batches(self.whole)
