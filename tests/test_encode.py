"""Invariants of cells, blocks, fill and projections."""

from __future__ import annotations

import numpy as np
import pytest
from hypothesis import given, settings
from hypothesis import strategies as st

from setvec.functions import seeds
from setvec.operators import kernels, theory
from setvec.plans.params import EncodeParams, collision_probability, frontier, params_search, params_single

DIM = 8


def unit(rng, n, dim=DIM):
    x = rng.standard_normal((n, dim)).astype(np.float32)
    return x / np.linalg.norm(x, axis=1, keepdims=True)


def one(vecs, params, side):
    return kernels.encode(vecs, np.zeros(len(vecs), np.int64), 1, params, side)[0].astype(np.float64)


bags = st.tuples(st.integers(0, 10**6), st.integers(1, 6), st.integers(1, 12), st.integers(0, 4), st.integers(1, 4))


@settings(max_examples=200, deadline=None)
@given(bags)
def test_score_lies_between_worst_and_best(case):
    seed, nq, nd, bits, reps = case
    rng = np.random.default_rng(seed)
    q, p = unit(rng, nq), unit(rng, nd)
    params = EncodeParams(DIM, bits, DIM, reps, seed)
    score = one(q, params, "query") @ one(p, params, "document") / reps
    product = q @ p.T
    assert product.min(1).sum() - 1e-4 <= score <= product.max(1).sum() + 1e-4
    if nd == 1:
        assert np.isclose(score, product.sum(), atol=1e-4)


@settings(max_examples=100, deadline=None)
@given(bags)
def test_sums_add_and_copies_change_nothing(case):
    seed, nq, nd, bits, reps = case
    rng = np.random.default_rng(seed)
    a, b, p = unit(rng, nq), unit(rng, nq + 1), unit(rng, nd)
    params = EncodeParams(DIM, bits, 4, reps, seed)
    both = one(np.concatenate([a, b]), params, "query")
    assert np.allclose(both, one(a, params, "query") + one(b, params, "query"), atol=1e-4)
    assert np.allclose(one(p, params, "document"), one(np.repeat(p, 2, 0), params, "document"), atol=1e-4)
    assert len(both) == params.width == (1 << bits) * 4 * reps


@settings(max_examples=100, deadline=None)
@given(bags)
def test_collision_identity_without_fill(case):
    seed, nq, nd, bits, reps = case
    rng = np.random.default_rng(seed)
    q, p = unit(rng, nq), unit(rng, nd)
    params = EncodeParams(DIM, bits, DIM, reps, seed, fill=False)
    cq, cp = kernels.cells_of(q, params), kernels.cells_of(p, params)
    want = 0.0
    for r in range(reps):
        for i in range(nq):
            same = cp[:, r] == cq[i, r]
            want += (p[same] @ q[i]).mean() if same.any() else 0.0
    assert np.isclose(one(q, params, "query") @ one(p, params, "document"), want, atol=1e-4)


def test_fill_takes_the_nearest_code_and_then_the_first_place():
    params = EncodeParams(2, 3, 2, 1, plane_law="int12", arithmetic="fixed")
    rng = np.random.default_rng(5)
    vecs = rng.integers(-1000, 1000, (4, 2))
    codes = kernels.cells_of(vecs, params)[:, 0]
    got = one(vecs, params, "document").reshape(8, 2)
    for cell in range(8):
        own = np.flatnonzero(codes == cell)
        if len(own):
            want = np.floor(vecs[own].sum(0) / len(own))
        else:
            want = vecs[min(range(4), key=lambda i: (int(codes[i] ^ cell).bit_count(), i))]
        assert (got[cell] == want).all()
    assert len(np.unique(kernels.cells_of(rng.integers(-1000, 1000, (5000, 2)), params))) <= 6


def test_no_fill_may_pass_the_best():
    worst = 0
    for seed in range(60):
        rng = np.random.default_rng(seed)
        q, p = unit(rng, 1), unit(rng, 3)
        params = EncodeParams(DIM, 3, DIM, 2, seed, fill=False)
        worst = max(worst, one(q, params, "query") @ one(p, params, "document") / 2 - (q @ p.T).max(1).sum())
    assert worst > 0.01


def test_one_cell_is_the_pooled_product():
    rng = np.random.default_rng(1)
    q, p = unit(rng, 5), unit(rng, 7)
    params = EncodeParams(DIM, 0, DIM, 1)
    assert np.isclose(one(q, params, "query") @ one(p, params, "document"), q.sum(0) @ p.mean(0), atol=1e-5)


def test_empty_bags_and_zero_vectors():
    params = EncodeParams(DIM, 3, 4, 2)
    assert not kernels.encode(np.zeros((0, DIM), np.float32), np.zeros(0, np.int64), 2, params, "document").any()
    assert (kernels.cells_of(np.zeros((1, DIM), np.float32), params) == 0).all()
    mixed = kernels.encode(unit(np.random.default_rng(0), 3), np.array([0, 2, 2]), 4, params, "document")
    assert not mixed[1].any() and not mixed[3].any() and mixed[0].any()


def test_slices_change_nothing(monkeypatch):
    rng = np.random.default_rng(2)
    vecs, owner = unit(rng, 60), np.sort(rng.integers(0, 20, 60))
    params = EncodeParams(DIM, 3, 4, 3, final_dim=10)
    whole = kernels.encode(vecs, owner, 20, params, "document")
    monkeypatch.setattr(kernels, "SLICE", 3 * params.cells * DIM)
    assert np.allclose(whole, kernels.encode(vecs, owner, 20, params, "document"), atol=1e-5)


def test_projections_keep_products_on_average():
    rng = np.random.default_rng(3)
    q, p = unit(rng, 4, 64), unit(rng, 6, 64)
    flat = EncodeParams(64, 2, 64, 1, fill=True)
    want = one(q, flat, "query") @ one(p, flat, "document")
    got = [one(q, flat.with_(proj_dim=16, seed=s), "query") @ one(p, flat.with_(proj_dim=16, seed=s), "document") for s in range(300)]
    base = [one(q, flat.with_(seed=s), "query") @ one(p, flat.with_(seed=s), "document") for s in range(300)]
    assert abs(np.mean(got) - np.mean(base)) < 0.15 and np.isfinite(want)


def test_signs_agree_like_angles():
    rng = np.random.default_rng(4)
    a, b = unit(rng, 2, 64)
    params = EncodeParams(64, 16, 64, 200)
    angle = np.arccos(a @ b)
    assert abs(theory.agreeing_signs(a, b, params) - (1 - angle / np.pi)) < 0.03
    near = (a + 0.2 * b) / np.linalg.norm(a + 0.2 * b)
    few = EncodeParams(64, 2, 64, 2000)
    assert abs(theory.same_bits(a, near, few) - collision_probability(float(a @ near), 2)) < 0.05


def test_center_partition_fill():
    rng = np.random.default_rng(6)
    vecs, centers = unit(rng, 3), unit(rng, 5)[None]
    params = EncodeParams(DIM, 0, DIM, 1, partition="center", n_centers=5)
    got = kernels.encode(vecs, np.zeros(3, np.int64), 1, params, "document", centers)[0].reshape(5, DIM)
    code = kernels.nearest_center(vecs, centers[0])
    for c in range(5):
        want = vecs[code == c].mean(0) if (code == c).any() else vecs[((vecs - centers[0, c]) ** 2).sum(1).argmin()]
        assert np.allclose(got[c], want, atol=1e-6)


def test_best_matching_concatenation():
    rng = np.random.default_rng(7)
    q, p = unit(rng, 4), unit(rng, 6)
    a, b = theory.oracle_concat(q, p)
    assert np.isclose(a @ b, kernels.maxsim(q, p, np.array([0]))[0], atol=1e-5)


def test_carving():
    rng = np.random.default_rng(8)
    for _ in range(100):
        q, p = unit(rng, 6), unit(rng, 9)
        sums, group = kernels.carve(q, 0.4)
        assert kernels.maxsim(sums, p, np.array([0]))[0] <= kernels.maxsim(q, p, np.array([0]))[0] + 1e-5
        assert sorted(set(group.tolist())) == list(range(len(sums))) and np.allclose(sums.sum(0), q.sum(0), atol=1e-5)
    q = unit(rng, 5)
    assert len(kernels.carve(q, 1.1)[0]) == 5 and len(kernels.carve(q, -1.1)[0]) == 1
    doubled = np.repeat(q, 2, 0)
    assert np.isclose(kernels.maxsim(kernels.carve(doubled, 0.999)[0], p, np.array([0]))[0], kernels.maxsim(doubled, p, np.array([0]))[0], atol=1e-4)
    a, b, c = (np.array([np.cos(t), np.sin(t)], np.float32) for t in (0.0, 0.6, 1.2))
    assert kernels.carve(np.stack([a, b, c]), 0.8)[1].tolist() == [0, 0, 1]


def test_params():
    assert [frontier(w, 64).width for w in (1280, 2560, 5120, 10240)] == [1280, 2560, 5120, 10240]
    p = frontier(1280, 64, fill=False)
    assert EncodeParams.from_json(p.to_json()) == p and not p.fill
    for bad in ({"proj_dim": 65}, {"partition": "other"}, {"arithmetic": "fixed"}, {"doc_block": "max"}, {"reps": 0}):
        with pytest.raises(ValueError):
            p.with_(**bad)
    assert params_single(0.5, 0.1, 10).reps == 1 and params_single(0.25, 0.1, 10).hash_bits > params_single(0.5, 0.1, 10).hash_bits
    assert params_search(0.5, 10, 64, 1000).reps < params_search(0.5, 10, 64, 10**6).reps


def test_seeds_are_functions_of_position():
    assert (seeds.planes(1, 2, 3, 4, "gaussian")[0] == seeds.planes(1, 5, 3, 4, "gaussian")[0]).all()
    flat = seeds.planes(42, 4, 8, 64, "int12")
    assert abs(flat.mean()) < 60 and 450 < flat.std() < 580
    signs = seeds.inner_signs(42, 4, 8, 64, "int12")
    assert set(np.unique(signs)) == {-1, 1} and abs(signs.mean()) < 0.1
