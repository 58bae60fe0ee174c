"""Coordinate solvers: sequential, replicated (static, dynamic, global dealing), hierarchical and the lock-free emulator."""

from __future__ import annotations

import contextlib
import json
import time
from collections.abc import Callable, Iterator
from dataclasses import asdict, dataclass, field, replace
from itertools import chain

import numpy as np
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from coordloom.operators import kernels, permute, stream, topology
from coordloom.operators.blocks import RESIDENT_CELLS, Packed, by_group, with_slots
from coordloom.operators.deal import busy_workers, global_ranks, own_worker
from coordloom.operators.permute import key
from coordloom.storage import CO_LOCATED, SMALL_BATCHES, Bucketed, settings

#: Above this many features w is no longer kept on the driver.
MAX_DRIVER_FEATURES = 10_000_000


@dataclass(frozen=True)
class TrainSpec:
    loss: str = "logistic"
    lam: float = 1e-3
    max_epochs: int = 50
    tol: float = 1e-3
    seed: int = 42
    workers: int = 1
    deal: str = "dynamic"  # static, dynamic (inside groups), global (moves all blocks every epoch)
    order: str = "md5"  # md5, feistel, affine, none
    merge: str | float = "add"  # add, average, or a factor gamma with sigma = 1
    syncs_per_epoch: int = 1
    shared_updates: bool = True
    tol_on: str = "alpha"  # or w
    threads: int = 0  # over 0: the lock-free emulator
    lost: bool = True
    loss_rate: float = 1.0
    staleness: int = 1  # rounds between two looks of a node at the writes of other nodes
    nodes: int = 1  # of the emulator's threads
    dual_pass: bool = False  # the libraries' dual descent instead of ours
    shrinking: bool = False
    resident: bool = True  # a single small group may stay in its task for the whole run

    def scales(self, busy: int) -> tuple[float, float]:
        """(sigma, gamma) for so many workers that have data."""
        if self.merge == "add":
            return float(busy), 1.0
        if self.merge == "average":
            return 1.0, 1.0 / busy
        return 1.0, float(self.merge)


@dataclass
class Model:
    w: np.ndarray
    alpha: DataFrame | None  # (slot, bid, alpha)
    meta: dict
    stored: Bucketed | None = None

    def release(self) -> None:
        """Delete the stored dual model; w stays."""
        if self.stored:
            self.stored.drop()
            self.alpha = self.stored = None

    def save(self, spark: SparkSession, path: str) -> None:
        rows = [(k, float(x)) for k, x in enumerate(self.w)]
        spark.createDataFrame(rows, "pos int, value double").coalesce(1).write.parquet(f"{path}/w.parquet")
        if self.alpha is not None:
            self.alpha.write.parquet(f"{path}/alpha.parquet")
        spark.createDataFrame([(json.dumps(self.meta),)], "value string").coalesce(1).write.text(f"{path}/meta.json")

    @staticmethod
    def load(spark: SparkSession, path: str) -> Model:
        rows = spark.read.parquet(f"{path}/w.parquet").orderBy("pos").collect()
        meta = json.loads(spark.read.text(f"{path}/meta.json").first()[0])
        try:
            alpha = Bucketed(spark.read.parquet(f"{path}/alpha.parquet"), "alpha", int(meta.get("groups", 1))).frame()
        except Exception as error:  # noqa: BLE001  a model of a primal solver has none
            if "PATH_NOT_FOUND" not in str(error):
                raise
            alpha = None
        return Model(np.array([r["value"] for r in rows]), alpha, meta)


HISTORY = "variant string, workers int, groups int, bucket int, epoch int, seconds double, rel_change double, status string, bytes_broadcast long, bytes_reduced long, collisions long, lost long"


@dataclass
class FitResult:
    model: Model
    rows: list[tuple] = field(default_factory=list)
    status: str = "max_epochs"

    @property
    def epochs(self) -> int:
        return len(self.rows)

    @property
    def seconds(self) -> float:
        return sum(r[5] for r in self.rows)

    def history(self, spark: SparkSession) -> DataFrame:
        return spark.createDataFrame(self.rows, HISTORY)


def arrow_rows(rows: Iterator) -> Iterator:
    """Rows of kernels.OUT as record batches of about two megabytes; record batches pass as they are."""
    import pyarrow as pa

    kinds = (pa.int32(), pa.int32(), pa.int32(), pa.int64(), pa.list_(pa.float64()), *[pa.float64()] * 4)
    names, held, cells = [c.split()[0] for c in kernels.OUT.split(", ")], [], 0

    def pack() -> pa.RecordBatch:
        flat = np.concatenate([r[4] for r in held])
        bounds = np.concatenate(([0], np.cumsum([len(r[4]) for r in held]))).astype(np.int32)
        columns = [pa.ListArray.from_arrays(pa.array(bounds), pa.array(flat)) if k == 4 else pa.array([r[k] for r in held], t) for k, t in enumerate(kinds)]
        return pa.RecordBatch.from_arrays(columns, names=names)

    for row in rows:
        if isinstance(row, pa.RecordBatch):
            yield row
            continue
        held.append(row)
        cells += len(row[4]) + 8
        if cells >= 1 << 18:
            yield pack()
            held, cells = [], 0
    if held:
        yield pack()


def sweep_frame(planned: DataFrame, sweep: kernels.Sweep, w: np.ndarray, extra: np.ndarray | None = None) -> DataFrame:
    """One task per group over rows in their order; w goes out as a broadcast of 8 d bytes, d bound by MAX_DRIVER_FEATURES."""
    shared = planned.sparkSession.sparkContext.broadcast((w, extra))

    def run(batches: Iterator) -> Iterator:
        w0, more = shared.value
        yield from arrow_rows(kernels.run_sweep(sweep, w0, more, batches))

    return planned.mapInArrow(run, kernels.OUT)


def resident(packed: Packed, spec: TrainSpec) -> bool:
    return spec.resident and packed.groups == 1 and packed.table is not None and packed.cells + packed.n <= RESIDENT_CELLS and spec.deal != "global"


def run_resident(packed: Packed, alpha: DataFrame | None, w: np.ndarray, tag: str, train: Callable) -> tuple[Bucketed, DataFrame, dict]:
    """``train(rows, w)`` in the one task that holds all rows: (its table, the new alpha, what it returned: (w, anything that JSON can say))."""
    shared = packed.frame.sparkSession.sparkContext.broadcast(w)
    frame, held = packed.frame.drop("eids"), (packed.n, packed.cells, packed.bucket, packed.slab)
    frame = frame.withColumn("alpha", F.lit(None).cast("array<double>")) if alpha is None else frame.join(alpha.hint("merge"), ["slot", "bid"], "left")

    def run(batches: Iterator) -> Iterator:
        rows = kernels.Resident(batches, *held)
        w_new, report = train(rows, shared.value.copy())
        text = np.frombuffer(json.dumps(report).encode(), dtype=np.uint8).astype(float)
        slot = rows.slot
        last = [(0, slot, 0, -1, w_new, 0.0, 0.0, 0.0, 0.0), (2, slot, 0, -1, text, 0.0, 0.0, 0.0, 0.0)]
        yield from arrow_rows(chain(rows.alphas(), last))

    table = Bucketed(frame.mapInArrow(run, kernels.OUT), tag, 1, ("kind",))
    found = {r["kind"]: np.array(r["vec"]) for r in table.plain().filter("kind <> 1").collect()}  # two rows
    report = json.loads(found[2].astype(np.uint8).tobytes().decode())
    return table, table.frame().filter("kind = 1").select("slot", "bid", F.col("vec").alias("alpha")), {"w": found[0], "report": report}


def _plan(packed: Packed, alpha: DataFrame | None, spec: TrainSpec, epoch: int, per_group: int) -> DataFrame:
    """The rows of an epoch in the order in which their tasks take them.

    Blocks and alpha are bucketed by their group and sorted by block, so the join needs neither an exchange nor a sort, and the
    order of the epoch is one sort inside each task. Run it under ``CO_LOCATED``. Only ``global`` dealing moves blocks.
    """
    frame = packed.frame.drop("eids")
    if "slot" not in frame.columns:
        frame = with_slots(frame, packed.slots)
    if alpha is None:
        frame = frame.withColumn("alpha", F.lit(None).cast("array<double>"))
    elif spec.deal == "global":
        frame = frame.join(alpha.drop("slot"), "bid", "left")
    else:
        frame = frame.join(alpha.hint("merge"), ["slot", "bid"], "left")
    if spec.deal == "global" and not spec.threads:
        workers = per_group * packed.groups
        dealt = global_ranks(packed.frame.sparkSession, packed.n_blocks, epoch, spec.seed, spec.order)
        wid = F.floor(F.col("rank") * workers / packed.n_blocks).cast("int")
        # alpha goes back to the block's own group, so the row keeps its slot
        moved = frame.join(dealt.hint("shuffle_hash"), "bid").withColumn("wid", wid).withColumn("gid", F.floor(F.col("wid") / per_group).cast("int"))
        return by_group(moved, packed.groups).sortWithinPartitions("wid", "rank").drop("rank")
    keyed = frame.withColumn("_key", key(F.col("bid"), epoch, spec.seed, spec.order, packed.n_blocks))
    if packed.table is None:
        keyed = by_group(keyed, packed.groups)
    if spec.deal == "static" and not spec.threads:
        return keyed.withColumn("wid", own_worker(packed.n_blocks, packed.groups, per_group)).sortWithinPartitions("wid", "_key", "bid").drop("_key")
    return keyed.sortWithinPartitions("_key", "bid").drop("_key")


def _run(packed: Packed, plan: DataFrame, sweep: kernels.Sweep, w: np.ndarray, tag: str, extra: np.ndarray | None = None) -> tuple[Bucketed, DataFrame, list]:
    """Run a pass: (its table, the new alpha as (slot, bid, alpha), the rows of the other kinds, one or two per group)."""
    out = sweep_frame(plan, sweep, w, extra)
    if sweep.deal == "global":
        out = out.repartition(packed.groups, "slot")
    table = Bucketed(out, tag, packed.groups, ("kind",))
    alpha = table.frame().filter("kind = 1").select("slot", "bid", F.col("vec").alias("alpha"))
    return table, alpha, sorted(table.plain().filter("kind <> 1").collect(), key=lambda r: (r["kind"], r["gid"]))


@contextlib.contextmanager
def turns(packed: Packed) -> Iterator[Callable]:
    """The passes of one run over the orders that the runs of a table share: ``one_pass(state, spec, epoch, sweep, w, tag, extra)`` gives the rows of
    the other kinds, and keeps the dual model as ``state["alpha"]`` in the table ``state["held"]``."""
    run = packed.orders.enter()

    def one_pass(state: dict, spec: TrainSpec, epoch: int, sweep: kernels.Sweep, w: np.ndarray, tag: str, extra: np.ndarray | None = None) -> list:
        table, state["alpha"], rest = stream.run_pass(packed, state["alpha"], spec, epoch, sweep, w, tag, run, extra)
        if state["held"]:
            state["held"].drop()
        state["held"] = table
        return rest

    try:
        yield one_pass
    finally:
        packed.orders.leave(run)


def fit(packed: Packed, spec: TrainSpec, warm: Model | None = None, variant: str | None = None) -> FitResult:
    """Epochs until the model's relative change falls under ``tol``."""
    if packed.d > MAX_DRIVER_FEATURES:
        raise ValueError("too many features for a model on the driver; hash them to fewer")
    if packed.slab > 1 and not resident(packed, spec) and not stream.streamed(packed, spec):
        raise ValueError("slabs are for runs that stay in one task; use pack")
    with settings(packed.frame.sparkSession, CO_LOCATED), settings(packed.frame.sparkSession, SMALL_BATCHES):
        return _fit(packed, spec, warm, variant)


@dataclass(frozen=True)
class _Shape:
    """What a run needs to know of its data; goes to the task when the run stays there."""

    n: int
    d: int
    n_blocks: int
    groups: int
    bucket: int
    unit: int

    @staticmethod
    def of(packed: Packed) -> _Shape:
        return _Shape(packed.n, packed.d, packed.n_blocks, packed.groups, packed.bucket, packed.unit)


def epoch_loop(shape: _Shape, spec: TrainSpec, w: np.ndarray, name: str, run_pass: Callable) -> tuple[np.ndarray, list[tuple], str]:
    """Epochs to the tolerance, wherever the passes run: ``run_pass(sweep, epoch, w)`` gives the groups' rows of kind 0. Returns (w, history, status)."""
    per_group = max(1, spec.workers // shape.groups)
    busy = shape.groups if spec.threads else busy_workers(shape.n_blocks, shape.groups, per_group, spec.deal)
    sigma, gamma = spec.scales(busy) if busy > 1 else (1.0, 1.0)
    kind = "lossy" if spec.threads else "dcd" if spec.dual_pass else "coordinate"
    full = None if spec.loss == "logistic" else (np.inf, -np.inf)  # leaves nothing out
    shrink, rows, outcome = full, [], "max_epochs"
    for epoch in range(spec.max_epochs):
        began, w_before, change, norm, collisions, lost, reduced = time.time(), w.copy(), 0.0, 0.0, 0, 0, 0
        for part in range(spec.syncs_per_epoch):
            sweep = kernels.Sweep(
                spec.loss, spec.lam, shape.n, shape.d, per_group, sigma, gamma, spec.shared_updates, kind, spec.threads or 1, spec.lost, spec.loss_rate, spec.staleness, spec.nodes,
                shrink if spec.shrinking else None, 0.0, (part, spec.syncs_per_epoch), spec.deal, shape.n_blocks, shape.groups, shape.unit, 1009 * spec.seed + epoch, spec.order == "none",
            )
            deltas = run_pass(sweep, epoch, w)
            w = w + gamma * sum((np.asarray(r[4]) for r in deltas), np.zeros(shape.d))
            reduced += 8 * shape.d * len(deltas)
            change, norm = change + sum(r[5] for r in deltas), sum(r[6] for r in deltas)
            if spec.threads:
                collisions, lost = collisions + int(sum(r[7] for r in deltas)), lost + int(sum(r[8] for r in deltas))
        if spec.tol_on == "w":
            change, norm = float(((w - w_before) ** 2).sum()), float((w**2).sum())
        rel = float(np.sqrt(change / norm)) if norm > 0 else 0.0
        bad = not np.all(np.isfinite(w))
        status = "diverged" if bad else "converged" if rel < spec.tol else "running"
        rows.append((name, spec.threads or per_group * shape.groups, shape.groups, shape.bucket, epoch + 1, time.time() - began, rel if not bad else float("inf"), status, 8 * shape.d * spec.syncs_per_epoch, reduced, collisions, lost))
        if status == "converged" and spec.shrinking and shrink != full:
            shrink = full  # look at all examples once more before stopping
            continue
        if status != "running":
            outcome = status
            break
        if spec.shrinking:
            shrink = _next_shrink(spec.loss, deltas)
    return w, rows, outcome


def _fit(packed: Packed, spec: TrainSpec, warm: Model | None, variant: str | None) -> FitResult:
    shape, name = _Shape.of(packed), variant or ("lock-free" if spec.threads else f"{spec.deal}")
    w = np.zeros(packed.d) if warm is None else warm.w.copy()
    state = {"alpha": None if warm is None else warm.alpha, "held": None}
    if resident(packed, spec):

        def train(rows: kernels.Resident, w: np.ndarray) -> tuple:
            keys = lambda epoch: lambda bids: permute.key_columns(bids, epoch, spec.seed, spec.order, shape.n_blocks)
            w, history, outcome = epoch_loop(shape, spec, w, name, lambda sweep, epoch, w: rows.run(sweep, keys(epoch), w))
            return w, [history, outcome]

        table, alpha, out = run_resident(packed, state["alpha"], w, "run", train)
        state = {"alpha": alpha, "held": table}
        w, rows, status = out["w"], [tuple(r) for r in out["report"][0]], out["report"][1]
    elif stream.streamed(packed, spec):
        if warm is not None and warm.alpha is not None:
            state["alpha"] = stream.by_example(packed, warm.alpha)
        with turns(packed) as one_pass:
            w, rows, status = epoch_loop(shape, spec, w, name, lambda sweep, epoch, w: [tuple(r[c.split()[0]] for c in kernels.OUT.split(", ")) for r in one_pass(state, spec, epoch, sweep, w, "epoch")])
        if state["alpha"] is not None:
            state["alpha"] = stream.by_row(packed, state["alpha"])
    else:

        def run_pass(sweep: kernels.Sweep, epoch: int, w: np.ndarray) -> list[tuple]:
            table, state["alpha"], deltas = _run(packed, _plan(packed, state["alpha"], spec, epoch, sweep.workers), sweep, w, "epoch")
            if state["held"]:
                state["held"].drop()
            state["held"] = table
            return [tuple(r[c.split()[0]] for c in kernels.OUT.split(", ")) for r in deltas]

        w, rows, status = epoch_loop(shape, spec, w, name, run_pass)
    meta = asdict(spec) | {"epochs": len(rows), "status": status, "groups": packed.groups}
    return FitResult(Model(w, state["alpha"], meta, state["held"]), rows, status)


def _next_shrink(loss: str, deltas: list[tuple]) -> tuple[float, float]:
    """What the next pass leaves out: logistic: slopes under a tenth of the worst; else beyond the extremes of this pass."""
    if loss == "logistic":
        return (0.1 * max(r[7] for r in deltas), 0.0)
    high, low = max(r[7] for r in deltas), min(r[8] for r in deltas)
    return (high if np.isfinite(high) else np.inf, low if np.isfinite(low) else -np.inf)


def fit_sequential(packed: Packed, spec: TrainSpec, warm: Model | None = None) -> FitResult:
    return fit(packed, replace(spec, workers=1, deal="dynamic", threads=0, syncs_per_epoch=1), warm, "sequential")


def fit_replicated(packed: Packed, spec: TrainSpec, warm: Model | None = None) -> FitResult:
    return fit(packed, spec, warm)


def fit_hierarchical(packed: Packed, spec: TrainSpec, warm: Model | None = None) -> FitResult:
    """Static over the groups the blocks were packed for, dynamic inside each."""
    return fit(packed, replace(spec, deal="dynamic"), warm, "hierarchical")


def fit_lossy_async(packed: Packed, spec: TrainSpec, threads: int, lost: bool = True, loss_rate: float = 1.0, staleness_nodes: int = 1) -> FitResult:
    """The lock-free solver, emulated. ``staleness_nodes``: the threads sit on so many nodes, which see each other's writes after as many rounds only."""
    nodes = max(1, staleness_nodes)
    return fit(packed, replace(spec, threads=threads, lost=lost, loss_rate=loss_rate, nodes=nodes, staleness=nodes), None, "lock-free" if lost else "atomic")


def fit_auto_spec(n: int, threads: int, machine: topology.Topology | None = None, **spec) -> tuple[TrainSpec, int, int]:
    """(spec, bucket size, groups) of the combined solver: the cache rule for buckets, the placement rule for groups."""
    machine = machine or topology.detect()
    placed = topology.plan_placement(min(threads, machine.nodes * machine.cores), machine)
    return TrainSpec(workers=threads, deal="dynamic", **spec), topology.choose_bucket(n, machine), len(placed)
