"""Worked examples and invariants of codes, angles, the torus and allocations."""

import math

import numpy as np
import pytest
from hypothesis import given, settings
from hypothesis import strategies as st

from raydescent.operators import codes, exact_coding, geometry, layout, torus
from raydescent.operators.lanes import coded_scheme
from raydescent.plans.params import CodeParams, Embedding, coprime_step, embed_parameters

VALID = [(8, 4, 2), (16, 8, 2), (16, 8, 4), (32, 16, 8), (64, 32, 4)]


def test_sign_table_of_four(spark):
    rows = {(r.alpha, r.beta): r.sign for r in codes.sign_table(spark, 4).collect()}
    assert ["".join("+-"[rows[a, b] < 0] for b in range(4)) for a in range(4)] == ["++++", "+-+-", "++--", "+--+"]


@pytest.mark.parametrize("n,k,t", VALID)
def test_tight_frame_and_weights(n, k, t):
    m = geometry.dense(CodeParams(n, k, t))
    assert np.allclose(m.T @ m, 2 * np.eye(k))
    assert ((m != 0).sum(axis=1) == t).all() and ((m != 0).sum(axis=0) == 2 * t).all()
    cos = np.abs(m @ m.T)
    off = cos[~np.eye(n, dtype=bool)]
    assert set(np.round(off, 9)) == {0.0, 0.5}
    assert ((np.abs(cos - 0.5) < 1e-9).sum(axis=1) == 4).all()
    assert math.isclose((cos**2).sum(), n * n / k)  # so no n > k rays are all at right angles


@pytest.mark.parametrize("n,k,t", [(4, 2, 2), (8, 4, 4), (8, 4, 1), (8, 6, 2), (16, 4, 2), (0, 4, 2)])
def test_rejected_sizes(n, k, t):
    with pytest.raises(ValueError):
        CodeParams(n, k, t).validate()


def test_relation_equals_matrix(spark):
    m = np.zeros((16, 8))
    for r in codes.projective_code(spark, 8, 4).collect():
        m[r.lane, r.theta] = r.sign * r.scale
    assert np.allclose(m, geometry.dense(CodeParams(16, 8, 4)))


def test_columns_of_a_hamming_code_are_heavy_and_its_rows_need_not_be(spark):
    base = geometry.weight_distribution(codes.identity_parity_code(spark)).collect()
    assert min(r.weight for r in base) == 1
    columns = geometry.weights_of(codes.mds_code(spark, 8, 4), "theta").collect()
    assert all(r.weight >= 8 - 4 + 1 for r in columns)


def test_prime_steps():
    assert [coprime_step(k) for k in (2, 3, 4, 5, 6, 7, 8, 30, 210, 2310)] == [3, 5, 3, 3, 5, 3, 3, 7, 11, 13]


def test_torus_trace(spark):
    got = torus.windows(spark, embed_parameters(5, 3, 2, 5), 4).collect()
    rows = [[next(r.code_row for r in got if (r.wave, r.lane) == (w, i)) for i in range(5)] for w in range(4)]
    assert rows == [[0, 1, 2, 3, 4], [5, 6, 7, 0, 1], [2, 3, 4, 5, 6], [7, 0, 1, 2, 3]]
    slots = [[next(r.code_col for r in got if (r.wave, r.lane, r.slot) == (w, 0, s)) for s in range(3)] for w in range(4)]
    assert slots == [[0, 1, 2], [1, 2, 3], [2, 3, 0], [3, 0, 1]]


@settings(max_examples=8, deadline=None)
@given(n=st.integers(5, 20), k=st.integers(4, 9))
def test_windows_are_permutations(n, k):
    e = embed_parameters(n, k, 2)
    assert isinstance(e, Embedding) and math.gcd(e.step, e.rows) == 1
    for wave in range(4):
        assert len({(i + wave * e.step) % e.rows for i in range(n)}) == n
        assert {(s + wave) % k for s in range(k)} == set(range(k))


def test_allocations(spark):
    held = {}
    for r in layout.allocate_shards(codes.projective_code(spark, 4, 2)).collect():
        held.setdefault(r.lane, set()).add(r.part_id)
    assert held == {0: {0, 1}, 1: {0, 1}, 2: {2, 3}, 3: {2, 3}, 4: {1, 2}, 5: {1, 2}, 6: {0, 3}, 7: {0, 3}}
    assert layout.pad_units(10, 4) == (3, 2)


def test_exact_coding_from_every_subset():
    from itertools import combinations

    code = exact_coding.exact_cyclic(7, 4, seed=1)
    for some in combinations(range(7), 4):
        coef = code.solve(list(some))
        assert np.allclose(coef @ code.matrix[list(some)], 1, atol=1e-6)
    with pytest.raises(ValueError):
        code.solve([0, 1])
    assert ((code.matrix != 0).sum(axis=1) == code.weight).all()


@pytest.mark.parametrize("mode", ["support", "pure"])
@pytest.mark.parametrize("n,k,t", VALID[:4])
def test_all_lanes_give_twice_the_sum(mode, n, k, t):
    rng = np.random.default_rng(0)
    grads = rng.standard_normal((k, t, 3))
    scheme = coded_scheme(CodeParams(n, k, t), mode, "unit")
    total = np.zeros((t, 3))
    for lane in range(n):
        message = sum(c * grads[p, g] for i, p, g, _, c in scheme.encode if i == lane)
        for i, _, g, c in scheme.decode:
            if i == lane:
                total[g] += c * message
    assert np.allclose(total, 2 * grads.sum(axis=0))
    assert all(len(scheme.shards_of(i)) == t for i in range(n)) or mode == "pure"


def test_mean_over_a_row_block_is_its_gradient():
    rng = np.random.default_rng(1)
    grads, p = rng.standard_normal((8, 4, 5)), CodeParams(16, 8, 4)
    scheme = coded_scheme(p)
    total = np.zeros((4, 5))
    for lane in range(4, 8):
        message = sum(c * grads[s, g] for i, s, g, _, c in scheme.encode if i == lane)
        for i, _, g, c in scheme.decode:
            if i == lane:
                total[g] += c * message / 4
    assert np.allclose(total, grads[p.shards_of(4)].sum(axis=0))
