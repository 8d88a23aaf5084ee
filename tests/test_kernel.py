"""Kernel: worked examples, edge cases, guarantees on random matrices; no Spark."""

import math

import numpy as np
import pytest
from hypothesis import given, settings
from hypothesis import strategies as st

from rowsketch.kernel.counters import CounterState
from rowsketch.kernel.paced import PacedState
from rowsketch.kernel.shrink import ShrinkState, expected_shrinks, shrink
from rowsketch.operators.measures import certificate_rows
from rowsketch.operators.sketch import Sketch, ell_for_cov, ell_for_heavy, ell_for_proj, guarantee
from rowsketch.sources import datagen

VARIANTS = ["per_row", "buffered", "paced"]


def sketch_of(a, ell, variant="buffered", **options):
    s = PacedState(ell, a.shape[1]) if variant == "paced" else ShrinkState(ell, a.shape[1], variant, **options)
    s.extend(a)
    rows = s.finish().copy()
    return Sketch(rows, ell, a.shape[1], s.n_rows, s.f2, s.shed, s.shrinks)


def holds(a, sk):
    bad = [r for r in certificate_rows(a.T @ a, sk) if not r[4]]
    assert not bad, bad


def test_pair_squares():
    a = np.array([[1.0, 1.0], [1.0, 0.0]])
    s = np.linalg.svd(a, compute_uv=False) ** 2
    assert np.allclose(s, [(3 + 5**0.5) / 2, (3 - 5**0.5) / 2])
    rows, delta = shrink(a, 2)
    assert math.isclose(delta, (3 - 5**0.5) / 2, rel_tol=1e-9)
    assert len(rows) == 1 and math.isclose(float(rows[0] @ rows[0]), 5**0.5, rel_tol=1e-9)
    assert math.isclose(2 * delta, 3 - float(rows[0] @ rows[0]), rel_tol=1e-9)


@pytest.mark.parametrize("svd", ["gram", "lapack", "arrowhead"])
def test_diagonal_per_row(svd):
    a = np.diag([3.0, 2.0, 1.0])
    sk = sketch_of(a, 3, "per_row", svd=svd)
    assert math.isclose(sk.shed, 1.0, rel_tol=1e-9)
    assert np.allclose(sk.spectrum, [8.0, 3.0])
    assert np.allclose(a.T @ a - sk.gram(), np.eye(3))


def test_number_of_shrinks():
    a = np.random.default_rng(0).standard_normal((2000, 60))
    for ell, n in ((20, 94), (50, 38)):
        s = ShrinkState(ell, 60)
        s.extend(a)
        assert s.shrinks == n == expected_shrinks(2000, ell)


@pytest.mark.parametrize("variant", VARIANTS)
@pytest.mark.parametrize("ell", [1, 2, 5, 20])
def test_guarantees(variant, ell):
    rng = np.random.default_rng(ell)
    for a in (rng.standard_normal((300, 12)), rng.standard_normal((100, 3)) @ rng.standard_normal((3, 30)), np.repeat(np.eye(6), 20, axis=0), np.zeros((10, 4)), rng.standard_normal((1, 7)), datagen.block_instance(2, 8, 40)):
        holds(a, sketch_of(a, ell, variant))


@pytest.mark.parametrize("variant", VARIANTS)
def test_exact_cases(variant):
    rng = np.random.default_rng(1)
    low = rng.standard_normal((200, 4)) @ rng.standard_normal((4, 25))
    for a in (rng.standard_normal((7, 30)), low, rng.standard_normal((300, 6))):
        sk = sketch_of(a, 8, variant)
        assert sk.shed <= 1e-9 * sk.f2
        assert np.allclose(sk.gram(), a.T @ a, atol=1e-8 * sk.f2)


@pytest.mark.parametrize("scale", [1e150, 1e-150])
def test_extreme_scale(scale):
    a = np.random.default_rng(2).standard_normal((50, 6)) * scale
    rows, delta = shrink(a, 4)
    assert np.isfinite(rows).all() and np.isfinite(delta)


@settings(max_examples=25, deadline=None)
@given(st.integers(1, 12), st.integers(1, 10), st.integers(0, 60), st.integers(0, 10_000))
def test_random_matrices(ell, d, n, seed):
    rng = np.random.default_rng(seed)
    a = rng.standard_normal((n, d)) * rng.choice([0.0, 1.0, 10.0], (n, 1))
    for v in VARIANTS:
        holds(a, sketch_of(a, ell, v))


def test_block_feeding_equals_rows():
    a = np.random.default_rng(3).standard_normal((137, 9))
    one, many = ShrinkState(4, 9), ShrinkState(4, 9)
    one.extend(a)
    for r in a:
        many.extend(r[None])
    assert np.array_equal(one.finish(), many.finish()) and one.shed == many.shed


def test_trace_of_losses():
    s = ShrinkState(5, 9, trace=True)
    s.extend(np.random.default_rng(4).standard_normal((200, 9)))
    assert s.trace
    for delta, before, after in s.trace:
        assert before - after >= 5 * delta - 1e-9


@pytest.mark.parametrize("factor", [2.0, 3.0, 4.5])
def test_buffer_factor(factor):
    a = np.random.default_rng(5).standard_normal((300, 20))
    holds(a, sketch_of(a, 6, buffer_factor=factor))


def test_merge_any_order():
    rng = np.random.default_rng(6)
    a = rng.standard_normal((400, 15))
    for seed in range(4):
        cut = np.sort(np.random.default_rng(seed).choice(400, 5, replace=False))
        parts = [sketch_of(p, 7) for p in np.split(a, cut)]
        np.random.default_rng(seed).shuffle(parts)
        whole = parts[0]
        for p in parts[1:]:
            whole = whole.merge(p)
        assert whole.n_rows == 400 and math.isclose(whole.f2, float((a * a).sum()), rel_tol=1e-9)
        holds(a, whole)


def test_merge_with_empty():
    sk = sketch_of(np.diag([3.0, 2.0, 1.0]), 3)
    same = sk.merge(Sketch(np.zeros((0, 3)), 3, 3, 0, 0.0, 0.0))
    assert np.allclose(same.gram(), sk.gram()) and math.isclose(same.shed, sk.shed)


def test_broken_kernels_are_caught():
    a = np.random.default_rng(7).standard_normal((300, 12))
    sk = sketch_of(a, 5)
    sk.shed *= 0.3
    assert not all(r[4] for r in certificate_rows(a.T @ a, sk))
    sk = sketch_of(a, 5)
    sk.rows = sk.rows * 3.0
    assert not all(r[4] for r in certificate_rows(a.T @ a, sk))


def test_paced_work_is_bounded():
    d, ell = 50, 6
    work = []
    for n in (500, 2000):
        s = PacedState(ell, d, trace=True)
        s.extend(np.random.default_rng(8).standard_normal((n, d)))
        work.append(max(s.flops))
        assert s.overruns == 0
    assert work[0] == work[1] <= 400 * d * ell


def test_counters_worked_example():
    s = CounterState(3)
    s.extend("aabc")
    assert s.counts == {"a": 1} and s.shed == 1 and s.estimate("b") == (0, 1)


def test_counters_equal_indicator_sketch():
    rng = np.random.default_rng(9)
    stream = rng.zipf(1.5, 800) % 30
    c, s = CounterState(8), ShrinkState(8, 30, "per_row")
    c.extend(stream.tolist())
    s.extend(np.eye(30)[stream])
    rows = s.finish()
    want = np.zeros(30)
    for k, v in c.counts.items():
        want[k] = v
    assert np.allclose(rows.T @ rows, np.diag(want), atol=1e-8) and math.isclose(s.shed, c.shed, abs_tol=1e-8)


@settings(max_examples=30, deadline=None)
@given(st.lists(st.integers(0, 15), max_size=200), st.integers(1, 10))
def test_counter_bounds(stream, ell):
    exact = {k: stream.count(k) for k in set(stream)}
    one, some = CounterState(ell), CounterState(ell)
    one.extend(stream)
    for at in range(0, len(stream), 17):
        part = stream[at : at + 17]
        some.add_counts({k: part.count(k) for k in set(part)})
    for s in (one, some):
        assert s.n == len(stream) and s.ell * s.shed <= s.n
        for k, f in exact.items():
            assert s.counts.get(k, 0) <= f <= s.counts.get(k, 0) + s.shed
        top = sorted(exact.values(), reverse=True)
        for k in range(min(ell, len(top))):
            assert s.shed * (ell - k) <= sum(top[k:])


def test_sizes():
    assert ell_for_cov(10, 0.1) == 20 and ell_for_proj(10, 0.1) == 110 and ell_for_heavy(0.1) == 11
    assert guarantee(20, 10) == (0.05, 2.0)


def test_instances():
    a = datagen.block_instance(4, 16, 400)
    assert math.isclose(float((a * a).sum()), 36.0)
    tail = np.sort(np.linalg.eigvalsh(a @ a.T))[::-1][4:].sum()
    assert tail <= 36 - (2 + datagen.ZETA) * 4 + 1e-9
    p = datagen.projection_instance(20, 40)
    assert np.allclose(sketch_of(p, 20).gram(), p.T @ p)
    b = datagen.binary_instance(4, 30)
    assert np.linalg.matrix_rank(np.vstack([sketch_of(b, 6).rows, b])) == np.linalg.matrix_rank(b)
    assert math.isclose(datagen.ZETA, (5**0.5 - 1) / 2)
    x = datagen.ZETA_AT
    assert math.isclose(2 * x * math.sqrt(1 - x * x) - x * x, datagen.ZETA)


def test_heavy_directions_and_rank():
    rng = np.random.default_rng(10)
    a = rng.standard_normal((500, 20)) * np.array([10, 6] + [0.5] * 18)
    sk = sketch_of(a, 12)
    heavy = sk.heavy_directions(eps=0.2)
    assert len(heavy) >= 2 and heavy[0]["certain"]
    for h in heavy:
        low, high = sk.quad_interval(h["vec"])
        true = float(((a @ h["vec"]) ** 2).sum())
        assert low - 1e-6 <= true <= high + 1e-6
    assert sk.choose_rank(50.0)[0] == 2
    half = sk.columns(list(range(10)))
    assert np.linalg.eigvalsh(a[:, :10].T @ a[:, :10] - half.gram()).max() <= half.shed + 1e-6
    w = rng.standard_normal((20, 5))
    turned = sk.right_multiply(w)
    assert np.linalg.eigvalsh((a @ w).T @ (a @ w) - turned.gram()).max() <= turned.shed + 1e-6
    holds(a, sk.reduce(6))
