"""The solvers to compare with: L-BFGS, Newton, exact ridge, gradient descent, SAG, dual descent with shrinking, online SGD, automatic choice, lasso."""

from __future__ import annotations

import time
from collections.abc import Iterator
from dataclasses import replace

import numpy as np
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from coordloom.operators import kernels, losses, permute
from coordloom.operators.blocks import RESIDENT_CELLS, Packed, regroup
from coordloom.operators.solvers import FitResult, Model, TrainSpec, _plan, _run, fit, resident, run_resident, sweep_frame, turns
from coordloom.operators.stream import streamed
from coordloom.storage import CO_LOCATED, SMALL_BATCHES, settings

GRAM_FEATURES = 2000
#: Numbers of a dense slice of examples in the sum for a Hessian.
HESSIAN_CELLS = 1 << 22


def objective_gradient(packed: Packed, w: np.ndarray, loss: str, lam: float, hessian: bool = False) -> tuple:
    """(objective, gradient, Hessian or None): one vector (or matrix) leaves each task."""
    shared, n, d = packed.frame.sparkSession.sparkContext.broadcast(w), packed.n, packed.d

    def run(batches: Iterator) -> Iterator:
        import pyarrow as pa

        v, total, grad, hess = shared.value, 0.0, np.zeros(d), np.zeros((d, d)) if hessian else None
        for batch in batches:
            if batch.num_rows and batch.column("idx").null_count and not hessian:  # dense: whole products
                x, y = (flat[at[0] : at[-1]] for at, flat in map(kernels.lists, (batch.column("val"), batch.column("y"))))
                x = x.reshape(len(y), -1)
                z = x @ v
                total += float(np.sum(losses.value(loss, z, y)))
                grad += losses.slope(loss, z, y) @ x
                continue
            row, idx, val, y = kernels.examples_of(batch)
            z = np.bincount(row, weights=val * v[idx], minlength=len(y))
            total += float(np.sum(losses.value(loss, z, y)))
            grad += np.bincount(idx, weights=val * losses.slope(loss, z, y)[row], minlength=d)
            if hessian:
                curved, step = losses.curvature(loss, z, y), max(1, HESSIAN_CELLS // max(1, d))
                for lo in range(0, len(y), step):  # a slice of examples at a time in dense form
                    a, b = np.searchsorted(row, (lo, lo + step))
                    x = np.zeros((min(step, len(y) - lo), d))
                    x[row[a:b] - lo, idx[a:b]] = val[a:b]
                    hess += x.T @ (curved[lo : lo + step, None] * x)
        yield pa.RecordBatch.from_arrays([pa.array([total]), pa.array([grad], pa.list_(pa.float64())), pa.array([hess.ravel() if hessian else None], pa.list_(pa.float64()))], names=["f", "g", "h"])

    with settings(packed.frame.sparkSession, SMALL_BATCHES):
        rows = packed.plain().select("y", "indptr", "idx", "val").mapInArrow(run, "f double, g array<double>, h array<double>").collect()  # one row per task
    grad = sum((np.array(r["g"]) for r in rows), np.zeros(d)) / n + lam * w
    hess = sum((np.array(r["h"]).reshape(d, d) for r in rows), np.zeros((d, d))) / n + lam * np.eye(d) if hessian else None
    return sum(r["f"] for r in rows) / n + lam / 2 * float(w @ w), grad, hess


def _result(name: str, packed: Packed, w: np.ndarray, steps: list[tuple[float, float]], done: bool) -> FitResult:
    rows = [(name, packed.groups, packed.groups, packed.bucket, k + 1, s, c, "converged" if done and k + 1 == len(steps) else "running", 8 * packed.d, 8 * packed.d * packed.groups, 0, 0) for k, (s, c) in enumerate(steps)]
    return FitResult(Model(w, None, {"solver": name}), rows, "converged" if done else "max_epochs")


def fit_lbfgs(packed: Packed, spec: TrainSpec, m: int = 10, gtol: float = 1e-6) -> FitResult:
    """Two-loop recursion with ``m`` pairs on the driver; backtracking; pairs with s.y under 1e-10 are skipped."""
    w, pairs, steps, done = np.zeros(packed.d), [], [], False
    f, g, _ = objective_gradient(packed, w, spec.loss, spec.lam)
    for _ in range(spec.max_epochs):
        began = time.time()
        if np.linalg.norm(g) < gtol * max(1.0, np.linalg.norm(w)):
            done = True
            break
        q, stack = g.copy(), []
        for s, y in reversed(pairs):
            a = (s @ q) / (s @ y)
            stack.append(a)
            q -= a * y
        if pairs:
            s, y = pairs[-1]
            q *= (s @ y) / (y @ y)
        for (s, y), a in zip(pairs, reversed(stack), strict=True):
            q += (a - (y @ q) / (s @ y)) * s
        t = 1.0
        while True:
            new = w - t * q
            f_new, g_new, _ = objective_gradient(packed, new, spec.loss, spec.lam)
            if f_new <= f - 1e-4 * t * float(g @ q) or t < 1e-8:
                break
            t /= 2
        s, y = new - w, g_new - g
        if s @ y > 1e-10:
            pairs = [*pairs, (s, y)][-m:]
        steps.append((time.time() - began, float(np.linalg.norm(s) / max(1e-300, np.linalg.norm(new)))))
        w, f, g = new, f_new, g_new
    return _result("lbfgs", packed, w, steps, done)


def fit_newton(packed: Packed, spec: TrainSpec, gtol: float = 1e-12) -> FitResult:
    """IRLS with the Gram matrix from the executors; d up to GRAM_FEATURES."""
    if packed.d > GRAM_FEATURES:
        raise ValueError("too many features for a Hessian on the driver")
    w, steps, done = np.zeros(packed.d), [], False
    for _ in range(spec.max_epochs):
        began = time.time()
        _, g, h = objective_gradient(packed, w, spec.loss, spec.lam, hessian=True)
        if np.linalg.norm(g) < gtol:
            done = True
            break
        move = np.linalg.solve(h, g)
        w = w - move
        steps.append((time.time() - began, float(np.linalg.norm(move) / max(1e-300, np.linalg.norm(w)))))
    return _result("newton", packed, w, steps, done)


def fit_ridge_exact(packed: Packed, lam: float) -> Model:
    _, g, h = objective_gradient(packed, np.zeros(packed.d), "ridge", lam, hessian=True)
    return Model(np.linalg.solve(h, -g), None, {"solver": "ridge-exact"})


def fit_gd(packed: Packed, spec: TrainSpec, rate: float = 1.0) -> FitResult:
    w, steps = np.zeros(packed.d), []
    for _ in range(spec.max_epochs):
        began = time.time()
        _, g, _ = objective_gradient(packed, w, spec.loss, spec.lam)
        w = w - rate * g
        steps.append((time.time() - began, float(rate * np.linalg.norm(g) / max(1e-300, np.linalg.norm(w)))))
        if steps[-1][1] < spec.tol:
            return _result("gd", packed, w, steps, True)
    return _result("gd", packed, w, steps, False)


def largest_norm(packed: Packed) -> float:
    """The largest squared norm of an example."""
    squares = F.transform("val", lambda v: v * v)
    per = F.transform(F.sequence(F.lit(1), F.size("y")), lambda k: F.aggregate(F.slice(squares, F.col("indptr")[k - 1] + 1, F.col("indptr")[k] - F.col("indptr")[k - 1]), F.lit(0.0), lambda a, v: a + v))
    return packed.plain().select(F.array_max(per).alias("q")).agg(F.max("q")).first()[0] or 0.0


def sag_loop(n: int, d: int, unit: int, bucket: int, spec: TrainSpec, rate: float, run_pass) -> tuple[np.ndarray, list[tuple], str]:
    """Passes to the tolerance; ``run_pass(sweep, epoch, w, average)`` gives the moves of w and of the average direction."""
    w, average, rows = np.zeros(d), np.zeros(d), []
    for epoch in range(spec.max_epochs):
        began = time.time()
        sweep = kernels.Sweep(spec.loss, spec.lam, n, d, 1, kind="sag", rate=rate, unit=unit, seed=1009 * spec.seed + epoch)
        move, turn = run_pass(sweep, epoch, w, average)
        w, average = w + move, average + turn
        rel = float(np.linalg.norm(move) / max(1e-300, np.linalg.norm(w)))
        rows.append(("sag", 1, 1, bucket, epoch + 1, time.time() - began, rel, "converged" if rel < spec.tol else "running", 16 * d, 16 * d, 0, 0))
        if rel < spec.tol:
            return w, rows, "converged"
    return w, rows, "max_epochs"


def fit_sag(packed: Packed, spec: TrainSpec) -> FitResult:
    """Sequential, in one task: step 1 / (L + lam) with L the largest curvature."""
    one, own = regroup(packed, 1), replace(spec, deal="dynamic")
    rate = 1.0 / (largest_norm(packed) * (0.25 if spec.loss == "logistic" else 1.0) + spec.lam)
    n, d, unit, bucket, n_blocks = packed.n, packed.d, packed.unit, packed.bucket, packed.n_blocks
    with settings(packed.frame.sparkSession, CO_LOCATED), settings(packed.frame.sparkSession, SMALL_BATCHES):
        if resident(one, own):

            def train(rows: kernels.Resident, w: np.ndarray) -> tuple:
                def run_pass(sweep, epoch, w, average):
                    keys = lambda bids: permute.key_columns(bids, epoch, spec.seed, spec.order, n_blocks)
                    moves = {r[0]: r[4] for r in rows.run(sweep, keys, w, average)}
                    return moves[0], moves[2]

                w, history, outcome = sag_loop(n, d, unit, bucket, own, rate, run_pass)
                return w, [history, outcome]

            table, _, out = run_resident(one, None, np.zeros(d), "sag", train)
            table.drop()
            return FitResult(Model(out["w"], None, {"solver": "sag"}), [tuple(r) for r in out["report"][0]], out["report"][1])
        state = {"alpha": None, "held": None}
        if streamed(one, own):
            with turns(one) as one_pass:

                def run_pass(sweep, epoch, w, average):
                    found = {r["kind"]: np.array(r["vec"]) for r in one_pass(state, own, epoch, sweep, w, "sag", average)}
                    return found[0], found[2]

                w, rows, status = sag_loop(n, d, unit, bucket, own, rate, run_pass)
            state["held"].drop()
            return FitResult(Model(w, None, {"solver": "sag"}), rows, status)

        def run_pass(sweep, epoch, w, average):
            table, state["alpha"], moves = _run(one, _plan(one, state["alpha"], own, epoch, 1), sweep, w, "sag", average)
            if state["held"]:
                state["held"].drop()
            state["held"], found = table, {r["kind"]: np.array(r["vec"]) for r in moves}
            return found[0], found[2]

        w, rows, status = sag_loop(n, d, unit, bucket, own, rate, run_pass)
    if state["held"]:
        state["held"].drop()
    return FitResult(Model(w, None, {"solver": "sag"}), rows, status)


def fit_dcd(packed: Packed, spec: TrainSpec, shrinking: bool = True) -> FitResult:
    """The libraries' single-threaded dual descent: examples permuted one by one, truncated inner solves, its own shrinking."""
    return fit(regroup(packed, 1), replace(spec, workers=1, deal="dynamic", dual_pass=True, shrinking=shrinking and spec.loss in ("logistic", "hinge", "smooth_hinge")), None, "dcd")


def fit_sgd(packed: Packed, spec: TrainSpec, rate: float = 0.5) -> FitResult:
    """One online pass."""
    began, one = time.time(), regroup(packed, 1)
    sweep = kernels.Sweep(spec.loss, spec.lam, packed.n, packed.d, 1, kind="sgd", rate=rate, unit=packed.unit, seed=1009 * spec.seed)
    with settings(packed.frame.sparkSession, CO_LOCATED), settings(packed.frame.sparkSession, SMALL_BATCHES):
        own = replace(spec, deal="dynamic")
        if streamed(one, own) and one.cells + one.n > RESIDENT_CELLS:
            state = {"alpha": None, "held": None}
            with turns(one) as one_pass:
                row = one_pass(state, own, 0, sweep, np.zeros(packed.d), "sgd")[0]
            state["held"].drop()
        else:
            row = sweep_frame(_plan(one, None, own, 0, 1), sweep, np.zeros(packed.d)).collect()[0]
    return _result("sgd", packed, np.array(row["vec"]), [(time.time() - began, 1.0)], True)


def fit_auto(packed: Packed, spec: TrainSpec, small: int = 200) -> FitResult:
    """IRLS for few features, L-BFGS for many (the original's rule isn't stated; this one is ours)."""
    out = fit_newton(packed, spec, 1e-8) if packed.d <= small and spec.loss in ("logistic", "ridge") else fit_lbfgs(packed, spec)
    out.rows = [("auto-" + r[0], *r[1:]) for r in out.rows]
    return out


def top_predictors(packed: Packed, p: int, loss: str) -> list[int]:
    """Columns with the largest gradient at 0 (to nine digits); ties by number."""
    _, g, _ = objective_gradient(packed, np.zeros(packed.d), loss, 0.0)
    return sorted(sorted(range(packed.d), key=lambda j: (-abs(round(float(g[j]), 9)), j))[:p])


def keep_columns(examples: DataFrame, columns: list[int]) -> DataFrame:
    """Sparse examples with these columns only, renumbered."""
    place = F.create_map(*[F.lit(x) for pair in ((c, k) for k, c in enumerate(columns)) for x in pair])
    pairs = F.filter(F.arrays_zip("idx", "val"), lambda e: F.array_contains(F.array(*map(F.lit, columns)), e["idx"]))
    return examples.withColumn("_p", pairs).select("eid", "y", F.transform("_p", lambda e: F.try_element_at(place, e["idx"])).alias("idx"), F.transform("_p", lambda e: e["val"]).alias("val"))


def gram(examples: DataFrame, target: str = "y") -> tuple[np.ndarray, np.ndarray, float, int]:
    """(X'X, X'y, y'y, n) of dense examples: each task adds up its own, one row leaves it."""
    first = examples.select(F.size("x")).first()
    d = first[0] if first else 0
    if d > GRAM_FEATURES:
        raise ValueError("too many features for a Gram matrix on the driver")

    def run(batches: Iterator) -> Iterator:
        import pyarrow as pa

        g, b, yy, n = np.zeros((d, d)), np.zeros(d), 0.0, 0
        for batch in batches:
            at, flat = kernels.lists(batch.column(0))
            x, y = flat[at[0] : at[-1]].reshape(-1, d), np.asarray(batch.column(1))
            g, b, yy, n = g + x.T @ x, b + x.T @ y, yy + float(y @ y), n + len(y)
        yield pa.RecordBatch.from_arrays([pa.array([g.ravel()], pa.list_(pa.float64())), pa.array([b], pa.list_(pa.float64())), pa.array([yy]), pa.array([n], pa.int64())], names=["g", "b", "yy", "n"])

    rows = examples.select(F.col("x").cast("array<double>"), F.col(target).cast("double")).mapInArrow(run, "g array<double>, b array<double>, yy double, n long").collect()  # one row per task
    total = lambda c: sum((np.array(r[c]) for r in rows), 0.0)
    return total("g").reshape(d, d), total("b"), float(sum(r["yy"] for r in rows)), sum(r["n"] for r in rows)


def fit_elastic_net(examples: DataFrame, l1: float, l2: float = 0.0, max_epochs: int = 100, tol: float = 1e-10, target: str = "y") -> tuple[np.ndarray, list[np.ndarray]]:
    """Primal coordinate descent over columns with covariance updates: one pass over the data, then d by d work. Returns beta and its path by epoch."""
    g, b, _, n = gram(examples, target)
    beta, path = np.zeros(len(b)), []
    for _ in range(max_epochs):
        before = beta.copy()
        for c in range(len(b)):
            rho = b[c] - g[c] @ beta + g[c, c] * beta[c]
            beta[c] = np.sign(rho) * max(abs(rho) - n * l1, 0.0) / (g[c, c] + n * l2)
        path.append(beta.copy())
        if np.linalg.norm(beta - before) <= tol * max(1e-300, np.linalg.norm(beta)):
            break
    return beta, path
