"""Registered workloads run to the tolerance, over whole sweeps."""

import numpy as np
import pytest

from coordloom.operators import baselines, metrics, solvers
from coordloom.plans import catalogue, workloads
from coordloom.sources import features


@pytest.fixture
def asked(monkeypatch):
    """(spec, packed) of the runs a query asks for; nothing is trained."""
    runs = []

    def fit(packed, spec, warm=None, variant=None):
        runs.append((spec, packed))
        return solvers.FitResult(solvers.Model(np.zeros(packed.d), None, {}), [("", spec.threads or spec.workers, packed.groups, packed.bucket, 1, 0.5, 0)])

    monkeypatch.setattr(solvers, "fit", fit)
    return runs


SWEEPS = {
    "wk_epochs_by_k": (lambda s, p: s.workers, [1, 2, 4, 8, 16]), "wk_dealing": (lambda s, p: (s.workers, s.deal), [(4, "dynamic"), (4, "static"), (16, "dynamic"), (16, "static")]), "wk_buckets": (lambda s, p: p.bucket, [1, 8, 16, 64]),
    "wk_hier": (lambda s, p: p.groups, [1, 2, 4]), "wk_bottlenecks": (lambda s, p: s.workers, [1, 1, 1, 4, 4, 4]), "wk_label_sorted": (lambda s, p: (s.workers, s.deal), [(4, "dynamic"), (4, "static"), (16, "dynamic"), (16, "static")]),
}


@pytest.mark.parametrize("name", SWEEPS)
def test_sweeps_are_whole_and_not_cut(spark, data_dir, asked, name):
    key, want = SWEEPS[name]
    catalogue.QUERIES[name](spark, data_dir)
    assert sorted(key(*run) for run in asked) == want
    assert all(s.max_epochs == 200 and s.tol == 1e-3 for s, _ in asked)


def test_epochs_by_workers_reach_the_tolerance(spark, data_dir):
    rows = {r["workers"]: r for r in catalogue.QUERIES["wk_epochs_by_k"](spark, data_dir).collect()}
    assert rows[1]["status"] == rows[4]["status"] == "converged" and rows[1]["epochs"] < rows[4]["epochs"]


@pytest.mark.parametrize(("name", "rows"), [("wk_lock_free_dense", 1000), ("wk_lock_free_sparse", 1000), ("wk_lock_free_line", 6000), ("wk_lock_free_order", 1500)])
def test_lock_free_runs_take_all_threads_and_the_rows_of_the_scale(spark, data_dir, asked, monkeypatch, name, rows):
    monkeypatch.setattr(workloads, "_reference", lambda packed, spec: 1.0)
    catalogue.QUERIES[name](spark, data_dir)
    assert sorted((s.threads, s.staleness) for s, _ in asked) == [(t, g) for t in (1, 2, 4, 8, 16, 32) for g in (1, 4)]
    assert all(s.max_epochs == 30 and s.tol == 1e-3 and p.n == rows for s, p in asked)


def test_drift_takes_all_threads_and_fixtures(spark, data_dir, asked, monkeypatch):
    monkeypatch.setattr(workloads.metrics, "certificate", lambda *_: {"drift": 0.0})
    catalogue.QUERIES["ls_drift"](spark, data_dir)
    assert sorted((p.n, s.threads) for s, p in asked) == sorted((n, t) for n in (1000, 1000, 6000, 1500) for t in (1, 2, 4, 8, 16, 32))
    assert all(s.max_epochs == 30 and s.tol == 1e-3 for s, _ in asked)


def test_comparison_has_all_solvers_workers_and_held_out_loss(spark, data_dir):
    examples = features.embed_matrix(spark, data_dir)
    rows = {r["variant"]: r for r in workloads.test_loss(spark, examples, 64, catalogue.LOGIT, workers=(1, 4), groups=2).collect()}
    assert set(rows) == {f"ours {k} workers" for k in (1, 4)} | {f"lock-free {k}" for k in (1, 4)} | {"dcd", "lbfgs", "sag", "sgd", "auto", "ours 4 workers 2 groups"}
    assert {rows[k]["status"] for k in ("ours 1 workers", "ours 4 workers", "dcd", "lbfgs", "sag", "auto")} == {"converged"}
    packed, held = workloads.held_out(examples, 64, 8)
    assert packed.n + held.count() == examples.count() and 0 < held.count() < packed.n
    best = metrics.evaluate(held, baselines.fit_newton(packed, solvers.TrainSpec("logistic", 0.01)).model)["logloss"]
    assert all(abs(rows[k]["test_loss"] - best) < 2e-3 for k in ("ours 4 workers", "dcd", "lbfgs", "auto"))


@pytest.mark.parametrize("fixture", ["line", "order", "wide"])
def test_ablations_are_registered_on_the_large_tables(fixture):
    assert {f"wk_{k}_{fixture}" for k in ("dealing", "buckets", "hier")} <= set(catalogue.QUERIES)


def test_orderings_on_the_sparse_orders(spark, data_dir):
    """Fig. 5 on the sparse stand-in: dynamic dealing needs fewer epochs than static, both reach the tolerance and one optimum."""
    packed = workloads.packed_fixture(spark, data_dir, "order", 8)
    rows = {r["variant"]: r for r in workloads.dealing(spark, packed, catalogue.LOGIT, (4,)).collect()}
    assert all(r["status"] == "converged" for r in rows.values())
    assert rows["dynamic k4"]["epochs"] < rows["static k4"]["epochs"]
    assert abs(rows["dynamic k4"]["objective"] - rows["static k4"]["objective"]) < 1e-3


def test_measures_read_a_history(spark):
    report = spark.createDataFrame([("static k1", 1, 8, 4.0, 0.5, "converged"), ("dynamic k1", 1, 8, 4.0, 0.5, "converged"), ("static k4", 4, 20, 4.0, 0.2, "converged"), ("dynamic k4", 4, 10, 2.0, 0.2, "wrong")], "variant string, workers int, epochs int, seconds double, seconds_per_epoch double, status string")
    got = {(r["measure"], r["variant"], r["workers"]): r["value"] for r in workloads.measures(report).collect()}
    assert got["speed-up", "dynamic", 4] == 2.0 and got["fewer epochs, percent", None, None] == 25.0 and got["efficiency", "dynamic", 4] == 0.625
    assert got["runs by status", "wrong", None] == 1 and got["best right run, seconds", "static", None] == 4.0


@pytest.mark.parametrize("fixture", ["line", "order", "wide"])
def test_comparison_is_registered_on_the_large_tables(fixture):
    assert f"wk_compare_{fixture}" in catalogue.QUERIES


def test_independent_runs_go_side_by_side(spark, data_dir, monkeypatch):
    """Each run is one task, so one after another leaves the other cores idle."""
    from threading import Barrier

    meet = Barrier(4, timeout=60)

    def fit(packed, spec, warm=None, variant=None):
        meet.wait()
        return solvers.FitResult(solvers.Model(np.zeros(packed.d), None, {}), [("", spec.workers, packed.groups, packed.bucket, 1, 0.5, 0)])

    monkeypatch.setattr(solvers, "fit", fit)
    assert [r["variant"] for r in catalogue.QUERIES["wk_dealing"](spark, data_dir).collect()] == ["static k4", "dynamic k4", "static k16", "dynamic k16"]


def test_drift_runs_of_all_fixtures_go_side_by_side(spark, data_dir, monkeypatch):
    """two fixtures with two runs each: all four at a time."""
    from threading import Barrier

    meet = Barrier(4, timeout=60)

    def fit(packed, spec, warm=None, variant=None):
        meet.wait()
        return solvers.FitResult(solvers.Model(np.zeros(packed.d), None, {}), [("", spec.threads, packed.groups, packed.bucket, 1, 0.5, 0)])

    monkeypatch.setattr(solvers, "fit", fit)
    monkeypatch.setattr(workloads.metrics, "certificate", lambda *_: {"drift": 0.0})
    rows = workloads.drift(spark, data_dir, ("synth_dense", "order"), solvers.TrainSpec("logistic", 1e-3, 30), (2, 4)).collect()
    assert [(r["fixture"], r["threads"]) for r in rows] == [("synth_dense", 2), ("synth_dense", 4), ("order", 2), ("order", 4)]


def test_lock_free_runs_of_a_comparison_have_the_epochs_of_the_others(spark, data_dir, monkeypatch):
    """they stopped at 30 epochs where all others may take 200."""
    asked, fit = [], solvers.fit

    def recorded(packed, spec, warm=None, variant=None):
        asked.append(spec)
        return fit(packed, solvers.replace(spec, max_epochs=1), warm, variant)

    monkeypatch.setattr(solvers, "fit", recorded)
    examples = features.embed_matrix(spark, data_dir)
    workloads.test_loss(spark, examples, 64, catalogue.LOGIT, workers=(1, 16), groups=1).collect()
    assert sorted(s.threads for s in asked if s.threads) == [1, 16]
    assert {s.max_epochs for s in asked} == {200} and {s.tol for s in asked} == {1e-3}
