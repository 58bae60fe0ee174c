"""Single-group runs of more values than a task holds.

The order of an epoch depends on its number, the seed and the dealing alone, so the rows are written once an epoch in that order for all runs that
draw it: dealt to parts by the range of their keys, in pieces of compact bytes. A run reads the parts one after another in one task, sorts each
in memory, and keeps only its dual model (8 bytes an example) and one part; nothing is sorted or spilled by run. At most two epochs of an order are kept.
"""

from __future__ import annotations

import threading
from collections.abc import Callable, Iterator
from functools import reduce
from itertools import chain

import numpy as np
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from coordloom.operators import kernels, permute
from coordloom.operators.flat import NARROW, Rows
from coordloom.storage import Bucketed, discard, settings, shared_dir

#: Examples whose dual model a task may hold (half a gigabyte).
EXAMPLES = 64 << 20
#: Bytes of a part in memory, of rows that a task deals out at once, and examples that go through a pass at once.
PART, DEALT, AT_ONCE = 96 << 20, 32 << 20, 1 << 16
#: Examples of a stored piece of the dual model.
ALPHAS = 1 << 16
#: Bytes that go to Python at once: pieces are up to some megabytes each.
FEW_BYTES = {"spark.sql.execution.arrow.maxBytesPerBatch": str(16 << 20)}
FIELDS = "at long, bid binary, key binary, y binary, sizes binary, idx binary, form binary, val binary"


def encoded(columns: list[np.ndarray]) -> tuple[bytes, bytes]:
    """(form, bytes) of float64 columns, bit by bit as they are: few distinct values as a book and codes."""
    import pyarrow as pa

    form, out = [], []
    for column in columns:
        bits = np.ascontiguousarray(column).view(np.int64)
        found = pa.array(bits).dictionary_encode()
        size = len(found.dictionary)
        width = 0 if size == 1 else 1 if size <= 1 << 8 else 2 if size <= 1 << 16 else 8
        form += [width, size if width < 8 else 0]
        if width < 8:
            out.append(np.asarray(found.dictionary).tobytes())
        if width:
            out.append(bits.tobytes() if width == 8 else np.asarray(found.indices).astype(np.uint8 if width == 1 else np.uint16).tobytes())
    return np.array(form, np.int32).tobytes(), b"".join(out)


def decoded(form, body, m: int) -> list[np.ndarray]:
    """The columns of ``encoded``, ``m`` values each."""
    lo, out = 0, []
    for width, size in np.frombuffer(form, np.int32).reshape(-1, 2).tolist():
        book = np.frombuffer(body, np.float64, size, lo)
        lo += 8 * size
        if not width:
            out.append(np.full(m, book[0]))
            continue
        codes = np.frombuffer(body, {1: np.uint8, 2: np.uint16, 8: np.float64}[width], m, lo)
        lo += width * m
        out.append(codes if width == 8 else book.take(codes))
    return out


def spans(rows: Rows, order: np.ndarray) -> tuple[np.ndarray, np.ndarray]:
    """(cuts of these rows laid end to end, their examples)."""
    sizes = rows.at[order + 1] - rows.at[order]
    cuts = np.concatenate(([0], np.cumsum(sizes)))
    return cuts, np.repeat(rows.at[order] - cuts[:-1], sizes) + np.arange(int(cuts[-1]))


class Layout:
    """What the tasks need to know of a table and of an order; ``static`` is the number of workers of static dealing, else 0."""

    def __init__(self, packed, epoch: int, seed: int, order: str, static: int):
        self.n, self.d, self.n_blocks, self.bucket, self.slab, self.dense = packed.n, packed.d, packed.n_blocks, packed.bucket, packed.slab, packed.dense
        self.epoch, self.seed, self.order, self.static = epoch, seed, order, static
        self.parts = max(1, min(1 << 12, self.n_blocks, -(-(packed.cells * (8 if packed.dense else 12) + 64 * packed.n) // PART)))
        self.index = np.uint16 if packed.d <= 1 << 16 else np.int32

    def keys(self, bids: np.ndarray) -> tuple[np.ndarray, ...]:
        return permute.key_columns(bids, self.epoch, self.seed, self.order, self.n_blocks)

    def part(self, bids: np.ndarray, lead: np.ndarray) -> np.ndarray:
        share = (lead >> np.uint64(32)).astype(np.int64) if self.order == "md5" else (lead.astype(np.float64) / self.n_blocks * 2.0**32).astype(np.int64)
        share = np.minimum(share, (1 << 32) - 1)
        own = bids * self.static // self.n_blocks if self.static else 0
        return ((own << 32) + share) * self.parts // (max(1, self.static) << 32)

    def pieces(self, rows: Rows) -> Iterator:
        """These rows as a piece for each part."""
        import pyarrow as pa

        bids = rows.bid.astype(np.int64)
        lead = self.keys(bids)[0]
        part = self.part(bids, lead)
        order = np.argsort(part, kind="stable")
        bounds = np.searchsorted(part[order], np.arange(self.parts + 1))
        for p, (lo, hi) in enumerate(zip(bounds[:-1].tolist(), bounds[1:].tolist(), strict=True)):
            if lo == hi:
                continue
            now = order[lo:hi]
            _, take = spans(rows, now)
            y, sizes, idx = rows.y[take], None, None
            if self.dense:
                x = rows.val.reshape(-1, self.d)[take]
                columns = list(x.T) if self.d <= NARROW else [x.ravel()]
            else:
                _, e = rows.entries(take)
                sizes, idx, columns = np.diff(rows.indptr)[take], rows.idx[e].astype(self.index).tobytes(), [rows.val[e]]
                sizes = None if (sizes == sizes[0]).all() else sizes.astype(np.int32).tobytes()
            form, val = encoded([*columns, y])
            fields = [p, 0, bids[now].tobytes(), lead[now].tobytes(), b"", sizes, idx, form, val]
            types = [pa.int32(), pa.int64(), *[pa.binary()] * 7]
            yield pa.RecordBatch.from_arrays([pa.array([v], t) for v, t in zip(fields, types, strict=True)], names=["part", *[f.split()[0] for f in FIELDS.split(", ")]])

    def dealt(self, batches: Iterator) -> Iterator:
        held, size = [], 0
        for batch in batches:
            if not batch.num_rows:
                continue
            rows = Rows.of(batch)
            held.append(rows.apart(self.bucket, self.slab) if self.slab > 1 else rows)
            size += 12 * len(rows.val) + 64 * len(rows.y)
            if size >= DEALT:
                yield from self.pieces(Rows.join(held))
                held, size = [], 0
        if held:
            yield from self.pieces(Rows.join(held))

    def whole(self, held: list[dict]) -> tuple:
        """(bid, leading key, at, indptr, idx, val, y) of the pieces of a part."""
        parts = []
        for f in held:
            bid = np.frombuffer(f["bid"], np.int64)
            counts = np.minimum(self.bucket, self.n - bid * self.bucket)
            m = int(counts.sum())
            idx = None if self.dense else np.frombuffer(f["idx"], self.index)
            if self.dense and self.d <= NARROW:
                *columns, y = decoded(f["form"], f["val"], m)
                val = np.stack(columns, axis=1).ravel() if columns else np.empty(0)
            else:
                val, y = _two(f["form"], f["val"], m * self.d if self.dense else len(idx), m)
            sizes = np.frombuffer(f["sizes"], np.int32) if f["sizes"] is not None else np.full(m, len(val) // max(1, m), np.int32)
            parts.append((bid, np.frombuffer(f["key"], np.uint64 if self.order == "md5" else np.int64), counts, sizes, idx, val, y))
        bid, key, counts, sizes, idx, val, y = (None if c[0] is None else np.concatenate(c) for c in zip(*parts, strict=True))
        cuts = lambda sizes: np.concatenate(([0], np.cumsum(sizes, dtype=np.int64)))
        return bid, key, cuts(counts), cuts(sizes), idx, val, y

    def rows_of(self, held: list[dict], alpha: np.ndarray) -> Iterator[Rows]:
        """The rows of a part in the order of the epoch, some at a time."""
        bid, key, at, indptr, idx, val, y = self.whole(held)
        held.clear()
        order = np.argsort(key)
        lead = key[order]
        if (lead[1:] == lead[:-1]).any():
            order = kernels.by_columns([*self.keys(bid), bid])
        wid = None
        if self.static:
            wid = bid * self.static // self.n_blocks
            order = order[np.argsort(wid[order], kind="stable")]
        ends = np.cumsum(np.diff(at)[order])
        lo = 0
        while lo < len(order):
            hi = max(lo + 1, int(np.searchsorted(ends, (ends[lo - 1] if lo else 0) + AT_ONCE, side="right")))
            now = order[lo:hi]
            lo = hi
            sizes = at[now + 1] - at[now]
            cuts = np.concatenate(([0], np.cumsum(sizes)))
            place = np.arange(int(cuts[-1]))
            take = np.repeat(at[now] - cuts[:-1], sizes) + place
            eid = np.repeat(bid[now] * self.bucket - cuts[:-1], sizes) + place
            if self.dense:
                values, cols, inner = val.reshape(-1, self.d)[take].ravel(), None, np.arange(len(take) + 1, dtype=np.int64) * self.d
            else:
                each = indptr[take + 1] - indptr[take]
                inner = np.concatenate(([0], np.cumsum(each)))
                e = np.repeat(indptr[take] - inner[:-1], each) + np.arange(int(inner[-1]))
                values, cols = val[e], idx[e]
            none = np.zeros(len(now), np.int32)
            yield Rows(none, none, bid[now], None if wid is None else wid[now], cuts, inner, None if cols is None else cols.astype(np.int32), values, y[take], alpha[eid])

    def read(self, batches: Iterator, alpha: np.ndarray) -> Iterator[Rows]:
        """The dual model comes first and goes to ``alpha``; then the parts in order, as rows."""
        held, part = [], -1
        for batch in batches:
            for k, p in enumerate(batch.column("part").to_pylist()):
                if p < part:
                    raise RuntimeError("the parts of an order came out of order")
                if p > part and held:
                    yield from self.rows_of(held, alpha)
                part = p
                if p < 0:
                    lo, values = batch.column("at")[k].as_py(), batch.column("alpha")[k].values
                    alpha[lo : lo + len(values)] = np.asarray(values)
                else:
                    held.append({name: batch.column(name)[k].as_buffer() if batch.column(name)[k].is_valid else None for name in ("bid", "key", "sizes", "idx", "form", "val")})
        if held:
            yield from self.rows_of(held, alpha)


def _two(form: bytes, body: bytes, values: int, m: int) -> tuple[np.ndarray, np.ndarray]:
    """(values, y) where the two columns differ in length."""
    (width, size), _ = np.frombuffer(form, np.int32).reshape(-1, 2).tolist()
    lo = 8 * size + width * values
    head, tail = np.frombuffer(form, np.int32)[:2].tobytes(), np.frombuffer(form, np.int32)[2:].tobytes()
    return decoded(head, memoryview(body)[:lo], values)[0], decoded(tail, memoryview(body)[lo:], m)[0]


class Order:
    """The rows of a table in the order of an epoch, in files by part."""

    def __init__(self, packed, layout: Layout):
        self.spark, self.layout, self.path = packed.frame.sparkSession, layout, shared_dir(packed.frame.sparkSession, "order")
        rows = packed.plain().select("slot", "gid", "bid", "y", "indptr", "idx", "val", F.lit(None).cast("array<double>").alias("alpha"))
        rows.mapInArrow(layout.dealt, f"part int, {FIELDS}").write.partitionBy("part").option("parquet.enable.dictionary", "false").option("parquet.block.size", str(8 << 20)).parquet(self.path)
        hadoop = self.spark._jvm.org.apache.hadoop.fs.Path
        files = hadoop(self.path).getFileSystem(self.spark.sparkContext._jsc.hadoopConfiguration())
        null = F.lit(None).cast("array<double>").alias("alpha")
        parts = [self.spark.read.schema(FIELDS).parquet(f"{self.path}/part={p}").select(F.lit(p).alias("part"), "*", null) for p in range(layout.parts) if files.exists(hadoop(f"{self.path}/part={p}"))]
        self.rows = reduce(DataFrame.union, parts)

    def frame(self, alpha: DataFrame | None) -> DataFrame:
        """One partition: the dual model (at, alpha), then the parts in order."""
        if alpha is None:
            return self.rows.coalesce(1)
        empty = [F.lit(None).cast("binary").alias(f.split()[0]) for f in FIELDS.split(", ")[1:]]
        return alpha.select(F.lit(-1).alias("part"), "at", *empty, "alpha").union(self.rows).coalesce(1)

    def drop(self) -> None:
        discard(self.spark, self.path)


class Orders:
    """The orders of a table, each made once for all runs that ask for it. A run waits where it would be more than an epoch ahead of the slowest,
    and what all have passed is deleted."""

    def __init__(self):
        self.turn, self.at, self.made = threading.Condition(), {}, {}

    def enter(self) -> object:
        with self.turn:
            run = object()
            self.at[run] = 0
            return run

    def leave(self, run: object) -> None:
        with self.turn:
            self.at.pop(run, None)
            self._tidy()

    def _tidy(self) -> None:
        first = min(self.at.values(), default=None)
        for key in [k for k, o in self.made.items() if o is not None and (first is None or k[0] < first)]:
            self.made.pop(key).drop()
        self.turn.notify_all()

    def get(self, run: object, key: tuple, make: Callable[[], Order]) -> Order:
        """``key`` starts with the epoch."""
        with self.turn:
            self.at[run] = key[0]
            self._tidy()
            self.turn.wait_for(lambda: key[0] <= min(self.at.values()) + 1 and (key not in self.made or self.made[key] is not None))
            if key in self.made:
                return self.made[key]
            self.made[key] = None
        try:
            made = make()
        except BaseException:
            with self.turn:
                del self.made[key]
                self.turn.notify_all()
            raise
        with self.turn:
            self.made[key] = made
            self.turn.notify_all()
        return made


def streamed(packed, spec) -> bool:
    return spec.resident and packed.groups == 1 and packed.table is not None and packed.n <= EXAMPLES and spec.deal != "global"


def run_pass(packed, alpha: DataFrame | None, spec, epoch: int, sweep: kernels.Sweep, w: np.ndarray, tag: str, run: object, extra: np.ndarray | None = None) -> tuple[Bucketed, DataFrame, list]:
    """A pass of one run: (its table, the new dual model as (at, alpha), the rows of the other kinds). ``run`` comes from ``packed.orders.enter``."""
    from coordloom.operators.solvers import arrow_rows

    static = sweep.workers if spec.deal == "static" and not spec.threads else 0
    layout = Layout(packed, epoch, spec.seed, spec.order, static)
    order = packed.orders.get(run, (epoch, spec.seed, spec.order, static, packed.bucket), lambda: Order(packed, layout))
    shared, n, bucket = packed.frame.sparkSession.sparkContext.broadcast((w, extra)), packed.n, packed.bucket

    def train(batches: Iterator) -> Iterator:
        w0, more = shared.value
        held, rest = np.zeros(n), []
        for out in kernels.run_sweep(sweep, w0, more, layout.read(batches, held)):
            if isinstance(out, tuple):
                if out[0] == 1:
                    held[out[3] * bucket : out[3] * bucket + len(out[4])] = out[4]
                else:
                    rest.append(out)
                continue
            at, vec = kernels.lists(out.column("vec"))
            sizes = np.diff(at)
            first = np.asarray(out.column("bid")) * bucket - (at[:-1] - at[0])
            held[np.repeat(first, sizes) + np.arange(int(sizes.sum()))] = vec[at[0] : at[-1]]
        pieces = ((1, 0, 0, lo, held[lo : lo + ALPHAS], 0.0, 0.0, 0.0, 0.0) for lo in range(0, n, ALPHAS))
        yield from arrow_rows(chain(pieces if sweep.kind != "sgd" else (), rest))

    with settings(packed.frame.sparkSession, FEW_BYTES):
        table = Bucketed(order.frame(alpha).mapInArrow(train, kernels.OUT), tag, 1, ("kind",))
    new = table.plain()
    return table, new.filter("kind = 1").select(F.col("bid").alias("at"), F.col("vec").alias("alpha")), sorted(new.filter("kind <> 1").collect(), key=lambda r: (r["kind"], r["gid"]))


def by_example(packed, alpha: DataFrame) -> DataFrame:
    """The dual model of stored rows, (slot, bid, alpha), as (at, alpha)."""
    return alpha.select((F.col("bid") * (packed.bucket * packed.slab)).alias("at"), "alpha")


def by_row(packed, alpha: DataFrame) -> DataFrame:
    """The dual model (at, alpha) as that of stored rows, (slot, bid, alpha)."""
    per, slots, n = packed.bucket * packed.slab, np.array(packed.slots, np.int32), packed.n
    stored = -(-n // per)

    def run(batches: Iterator) -> Iterator:
        import pyarrow as pa

        for batch in batches:
            for lo, values in zip(batch.column("at").to_pylist(), batch.column("alpha"), strict=True):
                values = np.asarray(values.values)
                hi = lo + len(values)
                cuts = np.unique(np.concatenate(([lo], np.arange(-(-lo // per) * per, hi, per), [hi])))
                bid = cuts[:-1] // per
                yield pa.RecordBatch.from_arrays([pa.array(slots[bid * len(slots) // stored]), pa.array(bid), pa.array(cuts[:-1] - bid * per), pa.ListArray.from_arrays(pa.array((cuts - lo).astype(np.int32)), pa.array(values))], names=["slot", "bid", "k", "alpha"])

    pieces = alpha.mapInArrow(run, "slot int, bid long, k long, alpha array<double>")
    if ALPHAS % per == 0:  # no row is cut
        return pieces.drop("k")
    return pieces.groupBy("slot", "bid").agg(F.sort_array(F.collect_list(F.struct("k", "alpha"))).alias("r")).select("slot", "bid", F.flatten("r.alpha").alias("alpha"))
