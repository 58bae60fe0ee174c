"""Solvers on the embeddings: metamorphic relations, invariants, the ordering of variants, agreement of optima."""

from dataclasses import replace

import numpy as np
import pytest
from pyspark.sql import functions as F

from coordloom.operators import baselines, blocks, metrics, permute, solvers
from coordloom.plans import workloads
from coordloom.sources import features

SPEC = solvers.TrainSpec("ridge", 0.01, 40, 1e-3)


@pytest.fixture(scope="module")
def examples(spark, data_dir):
    return features.embed_matrix(spark, data_dir)


@pytest.fixture(scope="module")
def packed(examples):
    return {g: blocks.pack(examples, examples.count(), 64, 5, g) for g in (1, 2)}


def test_pack_keeps_every_example(packed, examples):
    back = blocks.unpack(packed[2])
    assert back.select("eid", "y", F.col("val")).exceptAll(examples.select("eid", "y", F.col("x").alias("val"))).count() == 0
    assert back.count() == examples.count()


def test_one_worker_is_the_sequential_solver(packed):
    short = replace(SPEC, max_epochs=2, tol=0.0)
    seq, one, avg = solvers.fit_sequential(packed[1], short), solvers.fit(packed[1], replace(short, deal="static")), solvers.fit(packed[1], replace(short, merge="average"))
    lossless = solvers.fit_lossy_async(packed[1], short, 1)
    for other in (one, avg, lossless):
        assert np.allclose(seq.model.w, other.model.w, atol=1e-12)


def test_dealing_order_and_certificates(packed):
    runs = {"seq": (solvers.fit_sequential(packed[1], SPEC), 1), "static": (solvers.fit(packed[1], replace(SPEC, workers=4, deal="static")), 1), "dynamic": (solvers.fit(packed[1], replace(SPEC, workers=4)), 1), "hier": (solvers.fit_hierarchical(packed[2], replace(SPEC, workers=4)), 2)}
    epochs = {k: r.epochs for k, (r, _) in runs.items()}
    assert epochs["seq"] <= epochs["dynamic"] <= epochs["hier"] <= epochs["static"]
    exact = metrics.certificate(packed[1], baselines.fit_ridge_exact(packed[1], SPEC.lam), "ridge", SPEC.lam)["primal"]
    for r, g in runs.values():
        c = metrics.certificate(packed[g], r.model, "ridge", SPEC.lam)
        assert r.status == "converged" and c["drift"] < 1e-9 and -1e-12 <= c["gap"] < 1e-4 and c["primal"] - exact < 1e-5


def test_syncs_keep_the_invariant(packed):
    r = solvers.fit(packed[1], replace(SPEC, workers=4, syncs_per_epoch=2, max_epochs=2, tol=0.0))
    assert metrics.certificate(packed[1], r.model, "ridge", SPEC.lam)["drift"] < 1e-9


def test_lost_updates_break_the_invariant_and_atomic_ones_do_not(spark):
    df = features.synth_dense(spark, 200)
    p = blocks.pack(df, 200, 100, 1)
    spec = solvers.TrainSpec("logistic", 0.02, 2, 0.0)
    lost, atomic = solvers.fit_lossy_async(p, spec, 16), solvers.fit_lossy_async(p, spec, 16, lost=False)
    drift = [metrics.certificate(p, r.model, "logistic", 0.02)["drift"] for r in (lost, atomic)]
    assert drift[0] > 1e-3 and drift[1] < 1e-9 and lost.rows[-1][-1] > 0


def test_solvers_agree_on_logistic(packed):
    spec = replace(SPEC, loss="logistic", max_epochs=30)
    best = baselines.objective_gradient(packed[1], baselines.fit_newton(packed[1], spec).model.w, "logistic", spec.lam)[0]
    for r in (baselines.fit_lbfgs(packed[1], spec), baselines.fit_sag(packed[1], spec), solvers.fit(packed[2], replace(spec, workers=4))):
        assert baselines.objective_gradient(packed[1], r.model.w, "logistic", spec.lam)[0] == pytest.approx(best, abs=1e-3)


def test_against_the_ml_library(spark, packed, examples):
    from pyspark.ml.classification import LogisticRegression

    from coordloom.sources.io import to_vectors

    ml = LogisticRegression(fitIntercept=False, standardization=False, regParam=0.01, tol=1e-9).fit(to_vectors(examples, 64))
    ours = baselines.fit_newton(packed[1], replace(SPEC, loss="logistic")).model.w
    assert np.allclose(ml.coefficients.toArray(), ours, atol=1e-3)


def test_shrinking_reaches_the_same_optimum(packed):
    spec = replace(SPEC, loss="hinge", tol=1e-2)
    a, b = baselines.fit_dcd(packed[1], spec, True), baselines.fit_dcd(packed[1], spec, False)
    pa, pb = (metrics.certificate(packed[1], r.model, "hinge", spec.lam)["dual"] for r in (a, b))
    assert pa == pytest.approx(pb, abs=5e-3)


def test_model_round_trip_and_warm_start(spark, packed, tmp_path):
    r = solvers.fit(packed[1], replace(SPEC, tol=1e-5, max_epochs=20))
    r.model.save(spark, f"file://{tmp_path}/model")
    again = solvers.Model.load(spark, f"file://{tmp_path}/model")
    assert np.array_equal(again.w, r.model.w)
    assert solvers.fit(packed[1], replace(SPEC, tol=1e-3), again).epochs == 1


@pytest.mark.parametrize(("how", "groups"), [("static", 1), ("dynamic", 1), ("static", 2), ("dynamic", 2)])
def test_epochs_move_no_blocks(spark, packed, how, groups):
    """Epochs 1 and 2, with the dual model of the epoch before: neither an exchange nor a second sort above the scan of the blocks."""
    from coordloom.storage import CO_LOCATED, settings

    spec = replace(SPEC, deal=how, max_epochs=1, workers=4)
    model = solvers.fit(packed[groups], spec).model
    with settings(spark, CO_LOCATED | {"spark.sql.adaptive.enabled": "false"}):
        for epoch, alpha in ((0, None), (1, model.alpha), (2, model.alpha)):
            plan = solvers._plan(packed[groups], alpha, spec, epoch, 4 // groups)
            text = plan._jdf.queryExecution().executedPlan().toString()
            assert "Exchange" not in text and text.count("Sort [") == 1 and "Bucketed: true" in text, text
            assert plan.rdd.getNumPartitions() == groups


@pytest.mark.parametrize("spec", [
    replace(SPEC, workers=4), replace(SPEC, workers=4, deal="static", loss="logistic"), replace(SPEC, workers=3, syncs_per_epoch=2, merge="average"), replace(SPEC, workers=2, order="feistel"), replace(SPEC, threads=4, loss="logistic"),
    replace(SPEC, dual_pass=True, shrinking=True, loss="logistic"), replace(SPEC, order="affine", tol_on="w"),
])
def test_a_run_in_one_task_is_the_run_by_jobs(packed, spec):
    """Small single groups stay in their task: the same weights, history and dual model as one job a pass."""
    spec = replace(spec, max_epochs=4)
    inside, jobs = solvers.fit(packed[1], spec), solvers.fit(packed[1], replace(spec, resident=False))
    assert np.allclose(inside.model.w, jobs.model.w, atol=1e-13) and inside.status == jobs.status
    for a, b in zip(inside.rows, jobs.rows, strict=True):
        assert a[:5] == b[:5] and a[6] == pytest.approx(b[6]) and a[7:] == b[7:]
    sides = [{r["bid"]: r["alpha"] for r in m.model.alpha.collect()} for m in (inside, jobs)]
    assert sides[0].keys() == sides[1].keys() and all(np.allclose(sides[0][k], sides[1][k], atol=1e-13) for k in sides[0])


def test_settings_of_the_session_come_back(spark, packed):
    before = {k: spark.conf.get(k) for k in ("spark.sql.autoBroadcastJoinThreshold", "spark.sql.requireAllClusterKeysForCoPartition")}
    solvers.fit(packed[1], replace(SPEC, max_epochs=1))
    assert {k: spark.conf.get(k) for k in before} == before


def test_groups_have_buckets_of_their_own(spark):
    for g in (1, 2, 7, 40):
        slots = blocks.group_slots(spark, g)
        buckets = [r[0] for r in spark.createDataFrame([(s,) for s in slots], "s int").select(F.pmod(F.hash("s"), F.lit(g))).collect()]
        assert sorted(buckets) == list(range(g))


def test_gaps_and_doubles_in_the_numbers_are_refused(spark, examples):
    n = examples.count()
    for bad in (examples.filter("eid <> 7"), examples.filter("eid >= 10"), examples.withColumn("eid", F.when(F.col("eid") == 9, 8).otherwise(F.col("eid")))):
        with pytest.raises(Exception, match="number"):
            blocks.pack(bad, n, 64, 5)


def test_buckets_inside_rows(spark, data_dir):
    """Rows of 64 examples whose buckets of 8 are permuted: another order, the same optimum; stepping in chunks is stepping one by one."""
    from coordloom.operators import kernels
    from coordloom.plans import workloads

    df, d = workloads.fixture(spark, data_dir, "order")
    n = df.count()
    rows, inner = blocks.pack(df, n, d, 64), blocks.pack(df, n, d, 64, unit=8)
    spec = solvers.TrainSpec("logistic", 0.01)
    a, b = solvers.fit(rows, spec), solvers.fit(inner, spec)
    assert a.status == b.status == "converged" and np.abs(a.model.w - b.model.w).max() > 1e-9
    objective = [baselines.objective_gradient(inner, r.model.w, "logistic", 0.01)[0] for r in (a, b)]
    assert objective[0] == pytest.approx(objective[1], abs=1e-5)
    limit = kernels.CHUNK_CELLS
    block = next(kernels.blocks_of(iter([inner.plain().withColumn("alpha", F.lit(None).cast("array<double>")).limit(1).toArrow().to_batches()[0]])))
    sweep, ws, alphas = kernels.Sweep("logistic", 0.01, n, d, 1, unit=8, seed=3), [], []
    for cells in (limit, 0):
        kernels.CHUNK_CELLS = cells
        w = np.zeros(d)
        block.alpha = block.old.copy()
        kernels.step_block(sweep, block, w, __import__("coordloom.operators.losses", fromlist=["x"]).scalar_step("logistic"))
        ws.append(w)
        alphas.append(block.alpha)
    kernels.CHUNK_CELLS = limit
    assert np.allclose(ws[0], ws[1], atol=1e-12) and np.allclose(alphas[0], alphas[1], atol=1e-12)


def test_the_libraries_dual_descent_takes_its_own_way(packed):
    """Logistic: its weights differ from ours after three passes, its optimum doesn't; leaving examples out doesn't change it."""
    spec = replace(SPEC, loss="logistic", max_epochs=3, tol=0.0)
    ours, theirs = solvers.fit_sequential(packed[1], spec).model.w, baselines.fit_dcd(packed[1], spec).model.w
    assert np.abs(ours - theirs).max() > 1e-6
    best = baselines.fit_newton(packed[1], replace(spec, max_epochs=30)).model.w
    for shrinking in (True, False):
        r = baselines.fit_dcd(packed[1], replace(spec, max_epochs=50, tol=1e-4), shrinking)
        assert r.status == "converged" and np.abs(r.model.w - best).max() < 1e-2
        assert metrics.certificate(packed[1], r.model, "logistic", spec.lam)["drift"] < 1e-9


def test_threads_of_one_node_see_each_other(spark):
    """Placing the same threads on more nodes makes their reads staler: more is lost, the drift grows."""
    df = features.synth_dense(spark, 400)
    p = blocks.pack(df, 400, 100, 1)
    spec = solvers.TrainSpec("logistic", 0.02, 2, 0.0)
    runs = [solvers.fit_lossy_async(p, spec, 8, staleness_nodes=g) for g in (1, 4)]
    lost = [sum(r[-1] for r in run.rows) for run in runs]
    drift = [metrics.certificate(p, run.model, "logistic", 0.02)["drift"] for run in runs]
    assert lost[1] > lost[0] and drift[1] > drift[0]
    atomic = solvers.fit_lossy_async(p, spec, 8, lost=False, staleness_nodes=4)
    assert metrics.certificate(p, atomic.model, "logistic", 0.02)["drift"] < 1e-9


@pytest.mark.parametrize("order", ["md5", "feistel", "affine", "none"])
def test_global_dealing_is_one_group_dealt_anew(packed, order):
    spec = replace(SPEC, workers=4, max_epochs=2, tol=0.0, order=order)
    one, spread = solvers.fit(packed[1], spec), solvers.fit(packed[2], replace(spec, deal="global"))
    assert np.allclose(one.model.w, spread.model.w, atol=1e-12)


@pytest.mark.parametrize("loss", ["logistic", "ridge", "hinge", "squared_hinge", "smooth_hinge"])
def test_scalar_steps_equal_the_arrays(loss):
    from coordloom.operators import losses

    rng, step = np.random.default_rng(5), losses.scalar_step(loss)
    for _ in range(300):
        y, z, s = float(rng.choice([-1.0, 1.0])), float(rng.normal() * 5), float(10 ** rng.uniform(-3, 3))
        a = y * float(rng.uniform(0, 1))
        assert step(z, s, y, a, s) == pytest.approx(float(losses.step(loss, z, s, y, a, s)), abs=1e-11)


def test_auc_by_ranges_counts_ties(spark):
    rng = np.random.default_rng(8)
    rows = [(float(rng.choice([-1.0, 1.0])), float(m)) for m in rng.integers(0, 40, 500)]
    got = metrics.auc(spark.createDataFrame(rows, "y double, margin double")).first()[0]
    pos, neg = [m for y, m in rows if y > 0], [m for y, m in rows if y < 0]
    assert got == pytest.approx(np.mean([(p > q) + 0.5 * (p == q) for p in pos for q in neg]), abs=1e-12)


@pytest.mark.parametrize("n", [1, 3])
def test_tiny_inputs(spark, n):
    df = features.synth_dense(spark, n, 5)
    p = blocks.pack(df, n, 5, 2, 4)
    r = solvers.fit(p, solvers.TrainSpec("ridge", 0.1, 3, 0.0, workers=8))
    assert metrics.certificate(p, r.model, "ridge", 0.1)["drift"] < 1e-12


def test_feistel_column_equals_numpy(spark):
    for n in (1, 7, 1000):
        got = [r[0] for r in spark.range(n).orderBy("id").select(permute.key(F.col("id"), 3, 9, "feistel", n)).collect()]
        assert got == permute.feistel(np.arange(n), n, 3, 9).tolist()


def test_elastic_net_kills_columns(spark, data_dir):
    df = features.line_matrix(spark, data_dir).select(F.col("x")[1].alias("y"), F.array(F.col("x")[0], F.col("x")[2], F.col("x")[5]).alias("x"))
    beta, path = baselines.fit_elastic_net(df, 10.0)
    assert np.all(beta == 0) and len(path) >= 1


@pytest.mark.parametrize("sparse", [False, True])
def test_short_rows_are_stepped_together_with_equal_results(monkeypatch, sparse):
    """Rows of one example cost one product and one Gram matrix per chunk, not one each."""
    from coordloom.operators import kernels, losses

    def rows():
        rng = np.random.default_rng(3)
        for bid in range(200):
            b = kernels.Block()
            b.gid, b.slot, b.wid, b.bid = 0, 0, -1, bid
            b.idx = np.sort(rng.choice(12, 3, replace=False)).astype(np.int32) if sparse else None
            b.val, b.indptr, b.y = rng.normal(size=3), np.array([0, 3]), np.array([1.0 if rng.random() < 0.5 else -1.0])
            b.old = np.zeros(1)
            b.alpha = b.old.copy()
            yield b

    d = 12 if sparse else 3
    sweep = kernels.Sweep("logistic", 0.01, 200, d, 3, n_blocks=200, sigma=3.0)
    calls, whole = [], kernels.step_block
    monkeypatch.setattr(kernels, "step_block", lambda *a: (calls.append(1), whole(*a)))
    got = list(kernels.coordinate_sweep(sweep, np.zeros(d), rows()))
    assert len(calls) <= 6
    step, dealer, w, at, total, alphas = losses.scalar_step("logistic"), kernels.Dealer(sweep), None, None, np.zeros(d), []
    for b in rows():
        worker, _ = dealer(b)
        if worker != at:
            total, w, at = total + (0 if w is None else w / 3.0), np.zeros(d), worker
        whole(sweep, b, w, step)
        alphas.append(float(b.alpha[0]))
    total = total + w / 3.0
    assert [r[3] for r in got[:-1]] == list(range(200)) and np.allclose([float(r[4][0]) for r in got[:-1]], alphas, atol=1e-12)
    assert np.allclose(got[-1][4], total, atol=1e-12)


def flat_batch(n, d, bucket, sparse, seed=1):
    """Rows of ``bucket`` examples as they come from a table, dense with zeros or sparse."""
    import pyarrow as pa

    rng, rows = np.random.default_rng(seed), []
    for bid in range(-(-n // bucket)):
        m = min(bucket, n - bid * bucket)
        idx = np.concatenate([np.sort(rng.choice(d, 4, replace=False)) for _ in range(m)]).astype(np.int32) if sparse else None
        val = np.where(rng.random(m * (4 if sparse else d)) < 0.1, 0.0, rng.uniform(-1, 1, m * (4 if sparse else d)))
        rows.append((5, 0, bid, rng.choice([-1.0, 1.0], m), np.arange(0, len(val) + 1, len(val) // m).astype(np.int32), idx, val, None))
    doubles, ints = pa.list_(pa.float64()), pa.list_(pa.int32())
    kinds = {"slot": pa.int32(), "gid": pa.int32(), "bid": pa.int64(), "y": doubles, "indptr": ints, "idx": ints, "val": doubles, "alpha": doubles}
    return pa.RecordBatch.from_arrays([pa.array([r[k] for r in rows], t) for k, t in enumerate(kinds.values())], names=list(kinds))


SWEEPS = [("logistic", 1, "dynamic", 0, 1), ("logistic", 4, "static", 0, 1), ("ridge", 4, "dynamic", 0, 1), ("hinge", 1, "dynamic", 0, 1), *[("logistic", 1, "dynamic", t, g) for t in (1, 2, 8, 32) for g in (1, 4)]]


@pytest.mark.parametrize(("loss", "workers", "deal", "threads", "nodes"), SWEEPS)
@pytest.mark.parametrize(("d", "bucket", "sparse"), [(6, 8, False), (40, 1, False), (66, 3, True)])
def test_flat_passes_equal_those_over_blocks(monkeypatch, loss, workers, deal, threads, nodes, d, bucket, sparse):
    """Chunks solved together give the steps, the lost updates and the collisions of one example after another, and no row is touched by itself."""
    from coordloom.operators import flat, kernels, permute

    n = 3001
    batch = flat_batch(n, d, bucket, sparse)
    sweep = kernels.Sweep(loss, 0.1, n, d, workers, float(workers), kind="lossy" if threads else "coordinate", threads=threads or 1, nodes=nodes, staleness=nodes, deal=deal, n_blocks=batch.num_rows)
    got, want = kernels.Resident(iter([batch])), kernels.Resident(iter([batch.slice(0, 100), batch.slice(100)]))
    w, v = np.zeros(d), np.zeros(d)
    for epoch in range(2):
        keys = lambda bids: permute.key_columns(bids, epoch, 42, "md5", batch.num_rows)
        with monkeypatch.context() as m:
            m.setattr(kernels, "blocks_of", None)
            new = got.run(sweep, keys, w)[0]
        old = want._run_blocks(sweep, want.order(sweep, keys), v, None)[0]
        w, v = w + new[4], v + old[4]
        assert np.allclose(new[4:][0], old[4], rtol=0, atol=1e-12) and np.allclose(new[5:], old[5:], rtol=1e-9, atol=1e-9)
        assert np.allclose(got.rows.alpha, want.rows.alpha, rtol=0, atol=1e-11)
    whole = list(kernels.run_sweep(sweep, np.zeros(d), None, iter([batch.slice(k, 97) for k in range(0, batch.num_rows, 97)])) if deal == "dynamic" else [])
    if whole:  # rows as they come, in batches
        again = kernels.Resident(iter([batch])).run(sweep, lambda bids: (bids,), np.zeros(d))[0]
        assert np.allclose(whole[-1][4], again[4], rtol=0, atol=1e-12) and whole[-1][7:] == again[7:]
        assert [b for r in whole[:-1] for b in r.column("bid").to_pylist()] == list(range(batch.num_rows))


def test_key_columns_sort_as_keys():
    from coordloom.operators import permute

    numbers = np.arange(500)
    for order in permute.ORDERS:
        keys, columns = permute.keys_of(numbers, 3, 42, order, 500), permute.key_columns(numbers, 3, 42, order, 500)
        assert sorted(range(500), key=lambda k: keys[k]) == np.lexsort(columns[::-1]).tolist()


@pytest.mark.parametrize("kind", ["dcd", "sag", "sgd", "lossy"])
@pytest.mark.parametrize(("d", "bucket", "sparse"), [(6, 8, False), (40, 1, False), (300, 3, True)])
@pytest.mark.parametrize("loss", ["logistic", "ridge"])
def test_baselines_by_chunks_equal_those_over_blocks(monkeypatch, kind, d, bucket, sparse, loss):
    """The libraries' dual descent, SAG, SGD and sparse lock-free rounds of any width take no example by itself, with equal results."""
    from coordloom.operators import flat, kernels, permute

    if kind == "dcd" and loss == "ridge":
        pytest.skip("its left-out rule is the bounded losses'; steps stay one by one")
    n, lam = 12_001, 0.05
    batch = flat_batch(n, d, bucket, sparse)
    shapes = [(16, 1), (8, 4), (2, 4)] if kind == "lossy" and (sparse or d < 128) else [(1, 1)]
    for threads, nodes in shapes:
        sweep = kernels.Sweep(loss, lam, n, d, 1, kind=kind, threads=threads, nodes=nodes, staleness=nodes, n_blocks=batch.num_rows, rate=0.3, seed=7, shrink=(0.02, 0.0) if loss == "logistic" else None)
        if kind == "sgd":
            batches = [batch.slice(k, 900) for k in range(0, batch.num_rows, 900)]
            want = list(kernels.sgd_sweep(sweep, np.zeros(d), kernels.blocks_of(iter(batches))))[-1]
            alone = []
            with monkeypatch.context() as m:
                plain = flat.Gradients._one_by_one
                m.setattr(flat.Gradients, "_one_by_one", lambda self, rows, take: (alone.append(len(take)), plain(self, rows, take)))
                got = list(kernels.run_sweep(sweep, np.zeros(d), None, iter(batches)))[-1]
            assert np.allclose(got[4], want[4], rtol=0, atol=1e-11) and sum(alone) < n
            continue
        got, want = kernels.Resident(iter([batch])), kernels.Resident(iter([batch.slice(0, 100), batch.slice(100)]))
        w, v, g, h = np.zeros(d), np.zeros(d), np.zeros(d), np.zeros(d)
        for epoch in range(2):
            keys = lambda bids: permute.key_columns(bids, epoch, 42, "md5", batch.num_rows)
            with monkeypatch.context() as m:
                m.setattr(kernels, "blocks_of", None)
                m.setattr(kernels.Resident, "_run_blocks", None)
                m.setattr(kernels.dual_pass, "__call__", None)
                m.setattr(flat.Gradients, "_one_by_one", None)
                new = got.run(sweep, keys, w, g)
            old = want._run_blocks(sweep, want.order(sweep, keys), v, h)
            assert [r[0] for r in new] == [r[0] for r in old]
            assert all(np.allclose(a[4], b[4], rtol=0, atol=1e-11) and np.allclose(a[5:], b[5:], rtol=1e-9, atol=1e-9) for a, b in zip(new, old, strict=True))
            assert np.allclose(got.rows.alpha, want.rows.alpha, rtol=0, atol=1e-10)
            w, v = w + new[0][4], v + old[0][4]
            if kind == "sag":
                g, h = g + new[1][4], h + old[1][4]


def test_rows_are_ordered_by_one_column_where_it_has_no_ties(monkeypatch):
    """an epoch sorts its rows by the leading 64 bits of their keys; by all columns only if those have ties."""
    from coordloom.operators import kernels

    rng = np.random.default_rng(1)
    columns = [rng.permutation(500).astype(np.uint64), rng.integers(0, 9, 500), np.arange(500)]
    tied = [columns[1], *columns]
    assert kernels.by_columns(tied).tolist() == np.lexsort(tied[::-1]).tolist()
    want = np.lexsort(columns[::-1]).tolist()
    with monkeypatch.context() as m:
        m.setattr(np, "lexsort", None)
        assert kernels.by_columns(columns).tolist() == want


@pytest.mark.parametrize("sparse", [False, True])
def test_slabs_give_the_runs_of_single_rows(spark, sparse):
    """Many rows that are dealt lie in one stored row; runs, alphas and certificates are the same, and gaps are found."""
    n, d = 2500, 5
    df = spark.range(n).select(F.col("id").alias("eid"), F.when(F.rand(3) < 0.4, 1.0).otherwise(-1.0).alias("y"), F.array(*[F.rand(k) for k in range(d)]).alias("x"))
    if sparse:
        some = F.when(F.col("eid") % 3 == 0, F.array(F.lit(1), F.lit(4))).otherwise(F.array(F.lit(0), F.lit(2), F.lit(3)))
        df = df.select("eid", "y", some.alias("idx"), F.slice("x", 1, F.size(some)).alias("val"))
    df = df.repartition(7).localCheckpoint()
    slabs = blocks.pack_slabs(df, n, d, 16)
    assert slabs.slab == 64 and slabs.frame.count() == 3 and slabs.n_blocks == 157
    for bucket in (1, 8, 16):
        single, many = blocks.pack(df, n, d, bucket), blocks.rebucket(slabs, bucket)
        for spec in (solvers.TrainSpec("logistic", 0.01, 3, workers=4), solvers.TrainSpec("logistic", 0.01, 3, workers=4, deal="static"), solvers.TrainSpec("logistic", 0.01, 3, threads=4)):
            want, got = solvers.fit(single, spec), solvers.fit(many, spec)
            assert np.allclose(got.model.w, want.model.w, rtol=1e-12, atol=1e-14) and [r[6:] == pytest.approx(w[6:]) for r, w in zip(got.rows, want.rows, strict=True)]
        assert metrics.certificate(many, got.model, "logistic", 0.01) == pytest.approx(metrics.certificate(single, want.model, "logistic", 0.01), rel=1e-9, abs=1e-12)
        assert solvers.fit(many, spec, got.model).rows[0][6] == pytest.approx(solvers.fit(single, spec, want.model).rows[0][6], rel=1e-6)
    with pytest.raises(ValueError):
        solvers.fit(slabs, solvers.TrainSpec("logistic", 0.01, 1, resident=False))
    with pytest.raises(Exception, match="consecutive"):
        blocks.pack_slabs(df.filter("eid <> 700"), n - 1, d, 16)
    large = blocks.pack_slabs(df, n, d, 16, most=100)  # too large to stay in a task
    assert large.slab == 1 and large.frame.count() == 157


@pytest.mark.parametrize("sparse", [False, True])
def test_shared_orders_give_the_runs_of_rows_in_memory(spark, monkeypatch, sparse):
    """Above what a task holds, an epoch's order is written once for all runs; runs, alphas and certificates are the same and no order is left."""
    from pathlib import Path

    from coordloom.operators import stream
    from coordloom.sources import features

    n, d = 3000, 1000 if sparse else 30
    df = features.synth_sparse(spark, n) if sparse else features.synth_dense(spark, n, d)
    one = blocks.pack_slabs(df, n, d, 8)
    monkeypatch.setattr(blocks, "RESIDENT_CELLS", 100)
    spread = blocks.pack_runs(df, n, d, 8)
    assert spread.slab > 1 and len(spread.slots) > 1 and spread.cells == one.cells
    monkeypatch.setattr(stream, "PART", 1 << 17)
    made, make = [], stream.Order
    monkeypatch.setattr(stream, "Order", lambda packed, layout: made.append((layout.epoch, layout.static)) or make(packed, layout))
    specs = [solvers.TrainSpec("logistic", 0.01, 2, threads=t, nodes=g, staleness=g) for t, g in ((1, 1), (4, 1), (16, 4))] + [solvers.TrainSpec("logistic", 0.01, 2, workers=4), solvers.TrainSpec("ridge", 0.01, 2, workers=4, deal="static", order="feistel"), solvers.TrainSpec("logistic", 0.01, 2, dual_pass=True, shrinking=True)]
    want = [solvers.fit(one, s) for s in specs]
    monkeypatch.setattr(solvers, "RESIDENT_CELLS", 100)
    got = workloads.side_by_side(spark, [lambda s=s: solvers.fit(spread, s) for s in specs])
    assert sorted(made) == [(0, 0), (0, 4), (1, 0), (1, 4)]  # not once for each run
    for s, a, b in zip(specs, want, got, strict=True):
        assert np.allclose(b.model.w, a.model.w, rtol=1e-9, atol=1e-12) and [(r[7], *r[10:]) for r in b.rows] == [(r[7], *r[10:]) for r in a.rows]
        assert metrics.certificate(spread, b.model, s.loss, s.lam) == pytest.approx(metrics.certificate(one, a.model, s.loss, s.lam), rel=1e-9, abs=1e-12)
    assert solvers.fit(spread, specs[3], got[3].model).rows[0][6] == pytest.approx(solvers.fit(spread, specs[3], want[3].model).rows[0][6], rel=1e-6)
    root = Path(spark.conf.get("spark.checkpoint.dir").removeprefix("file://"))
    assert not spread.orders.made and not spread.orders.at and not list(root.glob("order-*"))
    with pytest.raises(Exception, match="consecutive"):
        blocks.pack_runs(df.filter("eid <> 700"), n - 1, d, 8)


def test_columns_come_back_bit_by_bit():
    from coordloom.operators import stream

    rng = np.random.default_rng(1)
    columns = [np.ones(70000), rng.integers(0, 9, 70000) / 7, rng.integers(0, 999, 70000) / 7, rng.random(70000), np.where(rng.random(70000) < 0.5, -0.0, 0.0)]
    form, body = stream.encoded(columns)
    assert [c.tobytes() for c in stream.decoded(form, body, 70000)] == [c.tobytes() for c in columns] and len(body) < 70000 * (1 + 2 + 8 + 1) + 20000
