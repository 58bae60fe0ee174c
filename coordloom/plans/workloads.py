"""The experiments, re-expressed on the given tables: each gives history rows or a summary DataFrame."""

from __future__ import annotations

import math
from collections.abc import Callable
from dataclasses import replace
from functools import partial

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from coordloom.operators import baselines, blocks, metrics, reports, solvers, topology
from coordloom.operators.blocks import Packed
from coordloom.operators.solvers import FitResult, TrainSpec
from coordloom.sources import features
from coordloom.storage import at_once, materialise


#: Threads of the lock-free runs.
THREADS = (1, 2, 4, 8, 16, 32)


def fixture(spark: SparkSession, sf_dir: str, name: str, n: int = 1000) -> tuple[DataFrame, int]:
    """(examples, number of columns)."""
    makers = {
        "line": (lambda: features.line_matrix(spark, sf_dir).select("eid", "y", "x"), 6), "embed": (lambda: features.embed_matrix(spark, sf_dir), 64), "order": (lambda: features.order_sparse(spark, sf_dir), 66), "text": (lambda: features.text_hash(spark, sf_dir).drop("y_toxic"), features.TEXT_DIM),
        "event": (lambda: features.event_sparse(spark, sf_dir), 107), "wide": (lambda: features.wide_line(spark, sf_dir), features.WIDE_DIM), "synth_dense": (lambda: features.synth_dense(spark, n), 100), "synth_sparse": (lambda: features.synth_sparse(spark, n), 1000),
    }
    make, d = makers[name]
    return make(), d


fixture_of = fixture


def packed_fixture(spark: SparkSession, sf_dir: str, name: str, bucket: int = 1, groups: int = 1, n: int = 1000) -> Packed:
    df, d = fixture(spark, sf_dir, name, n)
    df = materialise(df, "examples")  # made once for counting and packing
    return blocks.pack_runs(df, df.count(), d, bucket) if groups == 1 else blocks.pack(df, df.count(), d, bucket, groups)


def synthetic_rows(spark: SparkSession, sf_dir: str) -> int:
    """1k, 10k or 100k by scale: a sixth of ``lineitem``."""
    return max(1, round(features.read(spark, sf_dir, "lineitem").count() / 6))


def rows_per_block(n: int, workers: int, unit: int) -> int:
    """Examples of a stored row: many buckets, so that few rows pass between the JVM and Python, yet 32 rows or more for every worker to deal."""
    most = max(1, n // (32 * max(1, workers)))
    return max(unit, min(4096, most) // unit * unit)


def side_by_side(spark: SparkSession, jobs: list[Callable]) -> list:
    """All jobs at a time, whatever the cores: runs that share orders go through the epochs together; Spark queues their tasks."""
    return at_once(jobs, max(len(jobs), spark.sparkContext.defaultParallelism))


def together(spark: SparkSession, runs: list[tuple[str, Packed, Callable[[], FitResult]]]) -> list[tuple[str, Packed, FitResult]]:
    """Independent runs side by side, so that a run in one task doesn't leave the other cores idle; their seconds compare with one another only."""
    fits = side_by_side(spark, [make for _, _, make in runs])
    return [(name, packed, r) for (name, packed, _), r in zip(runs, fits, strict=True)]


def summary(spark: SparkSession, results: list[tuple[str, Packed, FitResult]], loss: str, lam: float) -> DataFrame:
    """One row per run: epochs, seconds, status, objective, drift."""
    rows = []
    objectives = at_once([partial(baselines.objective_gradient, packed, r.model.w, loss, lam) for _, packed, r in results], spark.sparkContext.defaultParallelism)
    for (name, packed, r), (objective, *_) in zip(results, objectives, strict=True):
        r.model.release()
        rows.append((name, r.rows[-1][1] if r.rows else 0, packed.groups, packed.bucket, r.epochs, r.status, r.seconds, r.seconds / max(1, r.epochs), objective))
    return spark.createDataFrame(rows, "variant string, workers int, groups int, bucket int, epochs int, status string, seconds double, seconds_per_epoch double, objective double")


def judged(report: DataFrame, reference: float, margin: float = 0.01) -> DataFrame:
    """Marks runs whose objective is off the reference: wrong although they may say converged."""
    off = F.abs(F.col("objective") - reference) > margin * abs(reference)
    return report.withColumn("status", F.when((F.col("status") == "converged") & off, "wrong").otherwise(F.col("status")))


def lock_free(spark: SparkSession, packed: Packed, spec: TrainSpec, threads: tuple[int, ...] = THREADS, nodes: tuple[int, ...] = (1, 4)) -> DataFrame:
    """The emulator by threads and nodes. Each run is one task, so they go side by side; their seconds compare with one another only."""
    asked = [(t, g) for t in threads for g in nodes]
    jobs = [lambda t=t, g=g: solvers.fit_lossy_async(packed, spec, t, staleness_nodes=g) for t, g in asked]
    *fits, reference = side_by_side(spark, [*jobs, partial(_reference, packed, spec)])  # the reference fills the cores that the last runs leave idle
    runs = [(f"lock-free t{t} n{g}", packed, r) for (t, g), r in zip(asked, fits, strict=True)]
    return judged(summary(spark, runs, spec.loss, spec.lam), reference)


def drift(spark: SparkSession, sf_dir: str, fixtures: tuple[str, ...], spec: TrainSpec, threads: tuple[int, ...] = THREADS) -> DataFrame:
    """|v - A alpha| and lost updates of the lock-free runs, by fixture and threads."""
    n = synthetic_rows(spark, sf_dir)
    packed = {name: packed_fixture(spark, sf_dir, name, n=n) for name in fixtures}
    asked = [(name, t) for name in fixtures for t in threads]
    fits = side_by_side(spark, [partial(solvers.fit_lossy_async, packed[name], spec, t) for name, t in asked])
    rows = []
    certificates = at_once([partial(metrics.certificate, packed[name], r.model, spec.loss, spec.lam) for (name, _), r in zip(asked, fits, strict=True)], spark.sparkContext.defaultParallelism)
    for (name, t), r, found in zip(asked, fits, certificates, strict=True):
        rows.append((name, t, found["drift"], r.rows[-1][-1], r.epochs, r.status))
    return spark.createDataFrame(rows, "fixture string, threads int, drift double, lost long, epochs int, status string")


def _reference(packed: Packed, spec: TrainSpec) -> float:
    w = baselines.fit_lbfgs(packed, replace(spec, max_epochs=max(60, spec.max_epochs))).model.w
    return baselines.objective_gradient(packed, w, spec.loss, spec.lam)[0]


def bottlenecks(spark: SparkSession, packed: Packed, spec: TrainSpec, workers: tuple[int, ...] = (1, 4)) -> DataFrame:
    """Without shared updates, without shuffling."""
    runs = []
    for k in workers:
        base = replace(spec, workers=k)
        runs += [(name, packed, partial(solvers.fit, packed, s)) for name, s in (("base", base), ("no-shared-updates", replace(base, shared_updates=False)), ("no-shuffling", replace(base, order="none")))]
    return summary(spark, together(spark, runs), spec.loss, spec.lam)


def partitions_sweep(spark: SparkSession, packed: Packed, spec: TrainSpec, workers: tuple[int, ...] = (1, 2, 4, 8, 16)) -> DataFrame:
    """Static dealing by number of workers."""
    return summary(spark, together(spark, [(f"static k{k}", packed, partial(solvers.fit, packed, replace(spec, workers=k, deal="static"))) for k in workers]), spec.loss, spec.lam)


def dealing(spark: SparkSession, packed: Packed, spec: TrainSpec, workers: tuple[int, ...] = (4, 16)) -> DataFrame:
    """Static against dynamic."""
    return summary(spark, together(spark, [(f"{d} k{k}", packed, partial(solvers.fit, packed, replace(spec, workers=k, deal=d))) for k in workers for d in ("static", "dynamic")]), spec.loss, spec.lam)


def buckets(spark: SparkSession, sf_dir: str, fixture: str, spec: TrainSpec, sizes: tuple[int, ...] = (1, 8, 16, 64)) -> DataFrame:
    """Bucket sizes, each bucket a row that is dealt; small tables are stored once for all sizes."""
    df, d = fixture_of(spark, sf_dir, fixture)
    df = materialise(df, "examples")  # made once for all sizes
    n, runs = df.count(), []
    first = blocks.pack_runs(df, n, d, math.lcm(*sizes))
    for b in sizes:
        p = blocks.rebucket(first, b) if first.slab > 1 else first if b == first.bucket else blocks.pack(df, n, d, b)
        runs.append((f"bucket {b}", p, partial(solvers.fit, p, spec)))
    return summary(spark, together(spark, runs), spec.loss, spec.lam)


def hierarchy(spark: SparkSession, sf_dir: str, fixture: str, spec: TrainSpec, groups: tuple[int, ...] = (1, 2, 4), bucket: int = 1) -> DataFrame:
    """Groups."""
    runs = []
    for g in groups:
        p = packed_fixture(spark, sf_dir, fixture, bucket, g)
        runs.append((f"groups {g}", p, partial(solvers.fit_hierarchical, p, spec)))
    return summary(spark, together(spark, runs), spec.loss, spec.lam)


def compare(spark: SparkSession, packed: Packed, spec: TrainSpec, workers: int = 4) -> DataFrame:
    """All solvers on one fixture."""
    runs = [
        ("ours 1 worker", packed, partial(solvers.fit_sequential, packed, spec)), (f"ours {workers} workers", packed, partial(solvers.fit, packed, replace(spec, workers=workers))), ("lock-free 16", packed, partial(solvers.fit_lossy_async, packed, spec, 16)),
        *((name, packed, partial(f, packed, spec)) for name, f in (("dcd", baselines.fit_dcd), ("lbfgs", baselines.fit_lbfgs), ("sag", baselines.fit_sag), ("auto", baselines.fit_auto))),
    ]
    return summary(spark, together(spark, runs), spec.loss, spec.lam)


def held_out(examples: DataFrame, d: int, bucket: int = 1) -> tuple[Packed, DataFrame]:
    """(packed training examples, held-out examples)."""
    from coordloom.sources.ids import densify

    examples = materialise(examples, "examples")
    train = densify(examples.filter(~metrics.is_test(F.col("eid"))).withColumnRenamed("eid", "_e"), ["_e"], "eid").drop("_e")
    return blocks.pack(train, train.count(), d, bucket), examples.filter(metrics.is_test(F.col("eid")))


def test_loss(spark: SparkSession, examples: DataFrame, d: int, spec: TrainSpec, workers: tuple[int, ...] = (1, 2, 4, 8, 16), bucket: int = 8, groups: int = 4) -> DataFrame:
    """Time to convergence and held-out mean loss of every solver, ours and the lock-free one by workers; ours also on the second configuration, of several groups."""
    p, held = held_out(examples, d, bucket)
    runs = [(f"lock-free {k}", p, partial(solvers.fit_lossy_async, p, spec, k)) for k in workers] + [(f"ours {k} workers", p, partial(solvers.fit, p, replace(spec, workers=k))) for k in workers]
    spread = blocks.regroup(p, groups)
    runs.append((f"ours {max(workers)} workers {groups} groups", spread, partial(solvers.fit_hierarchical, spread, replace(spec, workers=max(workers)))))
    runs += [(f.__name__.removeprefix("fit_"), p, partial(f, p, spec)) for f in (baselines.fit_dcd, baselines.fit_lbfgs, baselines.fit_sag, baselines.fit_sgd, baselines.fit_auto)]
    runs = together(spark, runs)
    best, *tests = at_once([partial(_reference, p, spec), *(partial(metrics.evaluate, held, r.model) for _, _, r in runs)], spark.sparkContext.defaultParallelism)
    losses = [(name, test["logloss"]) for (name, _, _), test in zip(runs, tests, strict=True)]
    report = judged(summary(spark, runs, spec.loss, spec.lam), best)
    return report.join(F.broadcast(spark.createDataFrame(losses, "variant string, test_loss double")), "variant")  # a row per run


def predictor_cap(spark: SparkSession, sf_dir: str, spec: TrainSpec, cap: int = 200) -> DataFrame:
    """The automatic solver and L-BFGS with all columns and with the strongest ``cap`` only, and their held-out loss."""
    df = features.text_hash(spark, sf_dir).drop("y_toxic")
    full, held = held_out(df, features.TEXT_DIM, 16)
    best = baselines.top_predictors(full, cap, spec.loss)
    few = blocks.pack(baselines.keep_columns(blocks.unpack(full), best), full.n, cap, 16)
    sides = (("all", full, held), (f"cap {cap}", few, baselines.keep_columns(held, best)))
    runs = [(f"{name} {k}", p, f(p, spec)) for k, p, _ in sides for name, f in (("lbfgs", baselines.fit_lbfgs), ("auto", baselines.fit_auto))]
    tests = {k: h for k, _, h in sides}
    losses = [(name, metrics.evaluate(tests[name.split(" ", 1)[1]], r.model)["logloss"]) for name, _, r in runs]
    return summary(spark, runs, spec.loss, spec.lam).join(F.broadcast(spark.createDataFrame(losses, "variant string, test_loss double")), "variant")  # a row per run


def measures(report: DataFrame) -> DataFrame:
    """C4, C4a, C7 and C16 over the history of W7: (measure, variant, workers, value)."""
    report = materialise(report.withColumn("variant", F.split("variant", " ")[0]), "report")
    rows = lambda df, name, value: df.select(F.lit(name).alias("measure"), *[F.col(c) if c in df.columns else F.lit(None).cast(t).alias(c) for c, t in (("variant", "string"), ("workers", "int"))], value.cast("double").alias("value"))
    out = rows(reports.speedup(report, "static"), "speed-up", F.col("speedup"))
    for column in ("epochs", "seconds"):
        out = out.unionByName(rows(reports.reduction(report, "static", "dynamic", column), f"fewer {column}, percent", F.col("percent")))
    out = out.unionByName(rows(reports.scaling_efficiency(report.filter("variant = 'dynamic'")), "efficiency", F.col("efficiency")))
    out = out.unionByName(rows(reports.best_valid(report, "static"), "best right run, seconds", F.col("seconds")))
    return out.unionByName(rows(reports.status_counts(report).withColumnRenamed("status", "variant"), "runs by status", F.col("n")))


def scaling(spark: SparkSession, sf_dir: str, fixture: str, spec: TrainSpec, groups: tuple[int, ...] = (1, 2, 4, 8), unit: int = 8, epochs: int = 2) -> DataFrame:
    """Seconds per epoch by groups, each a task of its own, with speed-up and efficiency."""
    df, d = fixture_of(spark, sf_dir, fixture)
    n, runs = df.count(), []
    first = blocks.pack(df, n, d, rows_per_block(n, spec.workers * max(groups), unit), 1, unit=unit)
    for g in groups:
        p = blocks.regroup(first, g)
        runs.append((f"groups {g}", p, solvers.fit(p, replace(spec, workers=spec.workers * g, max_epochs=epochs, tol=0.0, resident=False))))
    out = summary(spark, runs, spec.loss, spec.lam)
    base = out.filter("groups = 1").agg(F.first("seconds_per_epoch").alias("base"))  # one row
    return out.join(F.broadcast(base)).withColumn("speedup", F.col("base") / F.col("seconds_per_epoch")).withColumn("efficiency", F.col("speedup") / F.col("groups")).drop("base")


def label_sorted(spark: SparkSession, sf_dir: str, spec: TrainSpec, bucket: int = 5) -> DataFrame:
    """Examples sorted by label, the worst case for static dealing."""
    from coordloom.sources.ids import densify

    df = densify(features.embed_matrix(spark, sf_dir).withColumnRenamed("eid", "_e"), ["y", "_e"], "eid").drop("_e")
    p = blocks.pack(df, df.count(), 64, bucket)
    return dealing(spark, p, spec)


def cutoffs(counts: list[int], cutoff: int = 500_000) -> list[tuple[int, int, int]]:
    """(n, bucket by cache, bucket by the stated cut-off)."""
    machine = topology.detect()
    return [(n, topology.choose_bucket(n, machine), topology.choose_bucket(n, machine, cutoff)) for n in counts]
