"""The numeric layer without Spark: recurrences, interpolants, spectral forms, factors, costs."""

import numpy as np
import pytest

from delprop.functions import linearize
from delprop.functions.vector import pack, unpack
from delprop.operators import baselines, replay, spectral, train
from delprop.operators.capture import Capture, factor, piece_sums, rank_of
from delprop.plans.planner import Stats, choose, cost, step_bound
from delprop.spec import ModelSpec


def made(n=600, m=5, kind="linear", q=3, seed=0):
    draw = np.random.default_rng(seed)
    x = np.c_[draw.normal(size=(n, m - 1)), np.ones(n)]
    if kind == "linear":
        return x, x @ draw.normal(size=m) + 0.1 * draw.normal(size=n)
    if kind == "binary":
        return x, np.where(x @ draw.normal(size=m) + draw.logistic(size=n) > 0, 1.0, -1.0)
    return x, (x @ draw.normal(size=(m, q)) + draw.gumbel(size=(n, q))).argmax(1).astype(float)


def blocks_of(x, y, k, keep=None):
    own = np.arange(len(y)) * k // len(y)
    keep = np.ones(len(y), bool) if keep is None else keep
    return {b: (x[(own == b) & keep], y[(own == b) & keep]) for b in range(k)}


def captured(x, y, spec, k, path=None, upto=None, **options):
    whole = blocks_of(x, y, k)
    sums = {}
    if spec.kind == "linear":
        sums = {b: (len(v), lambda w, a=a: a.T @ (a @ w), a.T @ v) for b, (a, v) in whole.items()}
    else:
        for t in range(spec.tau if upto is None else upto):
            a, v = whole[t % k]
            c, d = piece_sums(a, v, path[t], spec, options)
            sums[t] = (len(v), lambda w, c=(c + c.T) / 2: c @ w, d)
    return Capture(spec, len(y), trajectory=np.zeros((0, 0)) if path is None else path, options=options), sums


CASES = {
    "linear": ModelSpec("linear", 5, lam=0.1, eta=0.05, tau=200, batch_size=120, schedule="cyclic"),
    "binary": ModelSpec("binary", 5, lam=0.1, eta=0.2, tau=200, batch_size=120, schedule="cyclic"),
    "softmax": ModelSpec("softmax", 5, q=3, lam=0.1, eta=0.2, tau=200, batch_size=120, schedule="cyclic"),
}


@pytest.mark.parametrize("kind,limit", [("linear", 1e-9), ("binary", 2e-3), ("softmax", 2e-2)])
@pytest.mark.parametrize("rate", [0.0, 0.01, 0.2])
def test_replay_equals_retraining(kind, limit, rate):
    spec, (x, y) = CASES[kind], made(kind=kind)
    gone = np.random.default_rng(1).random(len(y)) < rate
    w, path = train.descend(blocks_of(x, y, 5), spec, 5, keep=True)
    truth, _ = train.descend(blocks_of(x, y, 5, ~gone), spec, 5)
    capture, sums = captured(x, y, spec, 5, path)
    removed = {b: r for b, r in blocks_of(x, y, 5, gone).items() if len(r[1])}
    got = replay.run(capture, sums, removed)
    assert np.linalg.norm(got - truth) <= limit
    if rate == 0:
        assert np.linalg.norm(got - w) <= 1e-8


@pytest.mark.parametrize("kind", ["binary", "softmax"])
def test_replay_equals_the_survivors_rule(kind):
    spec, (x, y) = CASES[kind], made(kind=kind)
    gone = np.random.default_rng(2).random(len(y)) < 0.1
    _, path = train.descend(blocks_of(x, y, 5), spec, 5, keep=True)
    capture, sums = captured(x, y, spec, 5, path)
    removed = {b: r for b, r in blocks_of(x, y, 5, gone).items() if len(r[1])}
    want = replay.replay_survivors(blocks_of(x, y, 5, ~gone), path, spec, 5)
    assert np.allclose(replay.run(capture, sums, removed), want, atol=1e-10)


def test_empty_batch_only_shrinks():
    spec, (x, y) = CASES["linear"], made()
    gone = np.arange(len(y)) * 5 // len(y) == 2
    truth, _ = train.descend(blocks_of(x, y, 5, ~gone), spec, 5)
    capture, sums = captured(x, y, spec, 5)
    assert np.allclose(replay.run(capture, sums, {2: (x[gone], y[gone])}), truth, atol=1e-10)


def test_interpolant_error_and_edges():
    z = np.array([-25.0, -20.0, -1e-9, 0.0, 0.3, 19.99999, 20.0, 25.0])
    a, b = linearize.pieces(z)
    inside = np.abs(z) < 20
    assert np.abs(a * z + b - linearize.falling(z))[inside].max() <= 1.93e-11
    assert (a[~inside] == 0).all() and np.allclose(b[~inside], linearize.falling(np.clip(z[~inside], -20, 20)))
    fine = np.linspace(-6, 6, 20001)
    errors = []
    for cells in (2**8, 2**9, 2**10):
        a, b = linearize.pieces(fine, cells=cells)
        errors.append(np.abs(a * fine + b - linearize.falling(fine)).max())
    assert 3.5 < errors[0] / errors[1] < 4.5 and 3.5 < errors[1] / errors[2] < 4.5


def test_softmax_pieces_converge_and_meet_vertices():
    u = np.random.default_rng(0).normal(size=(500, 4)) * 2
    errors = []
    for dx in (0.4, 0.2, 0.1):
        a, c = linearize.softmax_simplex(u, dx)
        errors.append(np.abs(np.einsum("nij,nj->ni", a, u) + c - linearize.softmax(u)).max())
    assert errors[0] / errors[1] > 3 and errors[1] / errors[2] > 3
    a, c = linearize.softmax_tangent(u)
    assert np.allclose(np.einsum("nij,nj->ni", a, u) + c, linearize.softmax(u))
    vertex = np.array([[0.4, -0.8, 1.2, 0.0]])
    a, c = linearize.softmax_simplex(vertex, 0.4)
    assert np.allclose(np.einsum("nij,nj->ni", a, vertex) + c, linearize.softmax(vertex))


def test_spectral_linear_matches_the_loop_and_degrades_gently():
    spec, (x, y) = ModelSpec("linear", 5, lam=0.1, eta=0.05, tau=300), made(3000)
    c, q = np.linalg.eigh(-2 * x.T @ x)
    eigen = spectral.Eigen(q, c, 2 * x.T @ y, len(y))
    full, _ = train.descend({0: (x, y)}, spec, 1)
    assert np.allclose(spectral._finish(eigen, np.zeros(5), eigen.d, eigen.n, spec.start(), spec, 0, True), full, atol=1e-9)
    rates = ModelSpec("linear", 5, lam=0.1, eta=tuple(0.05 for _ in range(300)), tau=300)
    assert np.allclose(spectral._finish(eigen, np.zeros(5), eigen.d, eigen.n, spec.start(), rates, 0, True), full, atol=1e-9)
    errors = []
    for rate in (0.01, 0.05, 0.2):
        gone = np.random.default_rng(3).random(len(y)) < rate
        truth, _ = train.descend({0: (x[~gone], y[~gone])}, spec, 1)
        shift, d = -2 * ((x[gone] @ q) ** 2).sum(0), eigen.d - 2 * x[gone].T @ y[gone]
        errors.append(np.linalg.norm(spectral._finish(eigen, shift, d, (~gone).sum(), spec.start(), spec, 0, True) - truth))
        exact = spectral._finish(eigen, shift, d, (~gone).sum(), spec.start(), spec, 0, True, -2 * x[gone].T @ x[gone])
        assert np.allclose(exact, truth, atol=1e-9)
    assert errors[0] < errors[2] < 0.1


@pytest.mark.parametrize("kind", ["binary", "softmax"])
def test_spectral_logistic_is_near_retraining(kind):
    spec, (x, y) = CASES[kind], made(3000, kind=kind)
    gone = np.random.default_rng(4).random(len(y)) < 0.01
    _, path = train.descend(blocks_of(x, y, 5), spec, 5, keep=True)
    truth, _ = train.descend(blocks_of(x, y, 5, ~gone), spec, 5)
    at = 140
    capture, sums = captured(x, y, spec, 5, path, upto=at)
    c, d = piece_sums(x, y, path[at], spec, {})
    values, q = np.linalg.eigh((c + c.T) / 2)
    model = spectral.LogisticSpectral(capture, spectral.Eigen(q, values, d, len(y)), at)
    w = replay.run(capture, sums, {b: r for b, r in blocks_of(x, y, 5, gone).items() if len(r[1])}, at)
    got = spectral.finish_logistic(model, w, {0: (x[gone], y[gone])})
    assert np.linalg.norm(got - truth) < 0.05 * max(1, np.linalg.norm(truth))
    assert got @ truth / np.linalg.norm(got) / np.linalg.norm(truth) > 0.999


def test_rank_rules_and_truncation():
    s = np.array([1.0, 0.5, 0.02, 0.005])
    assert rank_of(s, 0.01) == 3 and rank_of(s, 0.01, "printed") == 1 and rank_of(s, 1e-9, "energy") == 4
    draw = np.random.default_rng(0)
    x = draw.normal(size=(40, 60)) * np.exp(-np.arange(60) / 8)
    gram, errors = x.T @ x, []
    for eps in (0.1, 1e-2, 1e-4):
        p, v = factor(gram, eps, "residual")
        errors.append(np.linalg.norm(p @ v.T - gram, 2) / np.linalg.norm(gram, 2))
        assert errors[-1] <= eps
    assert np.allclose(unpack(pack(gram), 60), gram)


def test_normal_equations_two_ways():
    x, y = made(400)
    gone = np.arange(400) < 30
    sums = (x.T @ x, x.T @ y, 400)
    a = baselines.normal_eq(sums, (x[gone], y[gone]), 0.1)
    assert np.allclose(a, baselines.normal_eq(sums, (x[gone], y[gone]), 0.1, "woodbury"))
    spec = ModelSpec("linear", 5, lam=0.1, eta=0.1, tau=3000)
    assert np.allclose(a, train.descend({0: (x[~gone], y[~gone])}, spec, 1)[0], atol=1e-6)


def test_costs_and_choice():
    few = Stats(n=581_012, m=54, batch=10_000, tau=500, removed=581, kind="binary")
    assert cost(few)["retrain"]["online"] > 5 * cost(few)["spectral"]["online"]
    assert choose(few) == "spectral"
    assert choose(Stats(n=23_149, m=47_236, batch=500, tau=3000, removed=23, kind="binary", nonzeros=75)) == "replay_sparse"
    assert choose(Stats(n=50_000, m=3072, batch=500, tau=1000, removed=50, kind="softmax", q=10, rank=100)) == "replay_lowrank"
    assert choose(Stats(n=1000, m=900, batch=10, tau=10, removed=900)) == "retrain"
    assert step_bound(10.0, 100, "linear", 0.1) == pytest.approx(1 / 0.3)


def test_spec_rejects_what_the_methods_cannot_do():
    with pytest.raises(ValueError):
        ModelSpec("linear", 3, penalty="l1")
    with pytest.raises(ValueError):
        ModelSpec("linear", 3, schedule="cyclic")
    with pytest.raises(ValueError):
        ModelSpec("softmax", 3)


def test_rank_update_of_more_removed_rows_than_features():
    """The inner system has the rank of the removed rows: 60,000 of them would else ask for a square matrix of 29 GB."""
    from delprop.operators import baselines

    draw = np.random.default_rng(3)
    x = draw.normal(size=(100_000, 3))
    y = x @ [1.0, -2.0, 0.5] + draw.normal(size=len(x))
    sums, gone = (x.T @ x, x.T @ y, len(y)), (x[:60_000], y[:60_000])
    truth = baselines.normal_eq(sums, gone, 0.1)
    assert np.allclose(baselines.normal_eq(sums, gone, 0.1, "woodbury"), truth)
    own = (gone[0].T @ gone[0], gone[0].T @ gone[1], 60_000)
    assert np.allclose(baselines.normal_eq_rank(sums, own, 0.1), truth)
    none = (np.zeros((3, 3)), np.zeros(3), 0)
    assert np.allclose(baselines.normal_eq_rank(sums, none, 0.1), baselines.normal_eq_sums(sums, none, 0.1))


def test_hash_of_vectors_is_the_portable_hash():
    from delprop.functions.hashing import uniform_of
    from delprop.functions.manyhash import uniforms

    ids, salts = [0, 7, 10, 99, 12345, 10**9, 2**60 - 1, 2**60 + 3, 10**18, 2**63 - 1, *range(1000, 1050)], ["a", "rm", "batch", "gumbel6", "x1499", "s" * 34]
    assert (uniforms(np.array(ids), salts) == [[uniform_of(i, s) for s in salts] for i in ids]).all()
    assert uniforms(np.array([-3]), ["a"])[0, 0] == uniform_of(-3, "a") and uniforms(np.array([], int), salts).shape == (0, 6)
