"""Coordinate steps, orders, topology: no Spark session needed."""

import numpy as np
import pytest
from hypothesis import given, settings
from hypothesis import strategies as st

from coordloom.operators import losses, permute, topology


@pytest.mark.parametrize("loss", losses.LOSSES)
def test_step_minimises_the_coordinate_objective(loss):
    rng = np.random.default_rng(1)
    for _ in range(40):
        y, z, s = rng.choice([-1.0, 1.0]), rng.normal() * 2, rng.uniform(0.05, 5)
        a = y * rng.uniform(0.05, 0.95)
        step = float(losses.step(loss, z, s, y, a, s))
        q = s  # with lam n = 1

        def objective(d):
            return 0.5 * q * d * d + d * z + losses.conjugate(loss, y, a + d)

        best = objective(step)
        for d in np.linspace(-3, 3, 401):
            b = y * (a + d)
            if loss in ("logistic", "hinge", "smooth_hinge") and not 0 <= b <= 1 or loss == "squared_hinge" and b < 0:
                continue
            assert best <= objective(d) + 1e-9


@pytest.mark.parametrize("loss", losses.LOSSES)
def test_conjugate_inequality(loss):
    rng = np.random.default_rng(2)
    y, z = rng.choice([-1.0, 1.0], 200), rng.normal(size=200) * 3
    a = y * rng.uniform(0, 1, 200)
    assert np.all(losses.value(loss, z, y) + losses.conjugate(loss, y, a) + a * z >= -1e-9)


def test_logit_root_is_exact():
    rng = np.random.default_rng(3)
    c, s, b = rng.normal(size=500) * 20, rng.uniform(1e-3, 1e3, 500), rng.uniform(0, 1, 500)
    u = losses.logit_root(c, s, b)
    assert np.max(np.abs(u + c + s * (1 / (1 + np.exp(-u)) - b)) / (1 + np.abs(u) + s)) < 1e-12


def test_hinge_without_norm_goes_to_its_bound():
    assert losses.step("hinge", 0.0, 0.0, 1.0, 0.25, 0.0) == pytest.approx(0.75)


@settings(max_examples=40, deadline=None)
@given(st.integers(1, 3000), st.integers(0, 5), st.integers(0, 1000))
def test_feistel_is_a_bijection(n, epoch, seed):
    assert np.array_equal(np.sort(permute.feistel(np.arange(n), n, epoch, seed)), np.arange(n))


def test_choose_bucket_at_the_cut():
    t = topology.Topology(1, 4, 64, 8000)
    assert topology.choose_bucket(1000, t) == 1 and topology.choose_bucket(1001, t) == 8
    assert topology.choose_bucket(500_001, topology.Topology(1, 4, 128), 500_000) == 16


def test_placement():
    x = topology.MACHINES["X"]
    assert topology.plan_placement(8, x, 2) == [(2, 8)]
    assert topology.plan_placement(9, x, 2) == [(2, 5), (0, 4)]
    assert sum(t for _, t in topology.plan_placement(32, x)) == 32
    with pytest.raises(ValueError):
        topology.plan_placement(33, x)


def test_detect_gives_something():
    t = topology.detect()
    assert t.nodes >= 1 and t.cores >= 1 and topology.bucket_size(t) >= 1


def test_md5_keys_by_vectors_are_those_of_hashlib():
    """a hash object for each number was the largest part of an epoch with one example a bucket."""
    import hashlib

    for numbers in (np.arange(11_000), np.array([0, 9, 10, 99, 10**18 - 1, 10**18, 2**63 - 1]), np.array([-1, 5]), np.empty(0, np.int64)):
        for tail in (b":0:42", b":199:-7", b":" + b"9" * 40):
            want = [hashlib.md5(b"%d%b" % (k, tail)).digest() for k in numbers.tolist()]
            high, low = permute.md5_columns(numbers, tail)
            assert [int(a).to_bytes(8, "big") + int(b).to_bytes(8, "big") for a, b in zip(high, low, strict=True)] == want
