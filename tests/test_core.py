"""Closed forms against finite differences and brute force; no Spark."""

import numpy as np
import pytest

from tidelabel.config import CleanConfig
from tidelabel.operators import core, influence, pruner, replay
from tidelabel.operators.core import LocalRows
from tidelabel.operators.measures import f1, fidelity, quality


def planted(n=300, c=3, d=6, seed=1):
    r = np.random.default_rng(seed)
    x = np.column_stack([r.normal(size=(n, d - 1)), np.ones(n)])
    truth = (x @ r.normal(size=(c, d)).T).argmax(axis=1)
    y = r.random((n, c))
    return x, truth, y / y.sum(axis=1, keepdims=True)


@pytest.fixture(scope="module")
def setting():
    x, truth, y = planted()
    val = planted(120, seed=2)
    cfg = CleanConfig(classes=3, lam=0.05, steps=80)
    rows = LocalRows(np.arange(300), x, y, np.zeros(300, bool), cfg.gamma)
    w = core.train_newton(rows, cfg)
    truth_val = (val[0] @ np.random.default_rng(1).normal(size=(3, 6)).T).argmax(axis=1)
    v = core.influence_vector(rows, core.validation_gradient(core.trusted_local(val[0], truth_val, w.shape[0]), w), w, cfg)
    return cfg, rows, w, v, val[0], truth_val, truth


def test_gradient_and_hessian_product_match_differences(setting):
    cfg, rows, w, *_ = setting
    u = np.random.default_rng(3).normal(size=w.shape)
    slope = (core.objective(rows, w + 1e-5 * u, cfg.lam) - core.objective(rows, w - 1e-5 * u, cfg.lam)) / 2e-5
    assert slope == pytest.approx((core.gradient(rows, w, cfg.lam)[0] * u).sum(), abs=1e-7)
    assert core.hvp(rows, w, u, cfg.lam) == pytest.approx(core.difference_hvp(rows, w, u, cfg.lam), abs=1e-6)
    assert core.hessian(rows, w, cfg.lam) @ u.ravel() == pytest.approx(core.hvp(rows, w, u, cfg.lam).ravel())


def test_solvers_agree(setting):
    cfg, rows, w, v, x, t, _ = setting
    g = core.validation_gradient(core.trusted_local(x, t, w.shape[0]), w)
    assert core.influence_vector(rows, g, w, cfg, "cg") == pytest.approx(v, abs=1e-6)
    assert core.influence_vector(rows, g, w, cfg, "sampled", 1.0) == pytest.approx(v, abs=1e-6)


def test_power_iteration_finds_largest_eigenvalue():
    r = np.random.default_rng(5)
    p = r.dirichlet([1, 1, 1, 1], 50)
    x = r.normal(size=(50, 4))
    exact = [np.linalg.eigvalsh(np.diag(a) - np.outer(a, a))[-1] * (b @ b) for a, b in zip(p, x)]
    assert core.hessian_norms(x, p, 500) == pytest.approx(exact, rel=1e-3)


def test_uplift_predicts_refits_and_the_other_sign_does_not(setting):
    cfg, rows, w, v, x, t, _ = setting
    ids, classes = list(range(0, 300, 25)), [i % 3 for i in range(12)]
    loss = lambda m: quality(core.trusted_local(x, t, m.shape[0]), m)["loss"]
    exact = influence.exact_influence(rows, loss, lambda r: core.train_newton(r, cfg), ids, classes)
    scores = influence.uplift_scores(rows.x, rows.y, w, v, cfg.gamma)
    found = fidelity(np.array([scores[i, c] for i, c in zip(ids, classes)]), exact)
    assert found["corr"] > 0.99 and 0.85 < found["slope"] < 1.15
    s = rows.x @ v.T
    wrong = -(rows.y * s).sum(axis=1, keepdims=True) + s + (1 - cfg.gamma) * ((core.softmax(rows.x @ w.T) - rows.y) * s).sum(axis=1, keepdims=True)
    assert fidelity(np.array([wrong[i, c] for i, c in zip(ids, classes)]), exact)["corr"] < 0


def test_deletion_effect_is_minus_gamma_times_printed(setting):
    cfg, rows, w, v, x, t, _ = setting
    printed = influence.deletion_scores(rows.x, rows.y, w, v)
    effect = influence.deletion_scores(rows.x, rows.y, w, v, cfg.gamma, "effect")
    assert effect == pytest.approx(-cfg.gamma * printed)
    base, out = quality(core.trusted_local(x, t, w.shape[0]), w)["loss"], []
    for i in range(0, 300, 30):
        m = np.arange(300) != i
        # the row's weight goes to nought while N stays
        y, weight = rows.y.copy(), None
        kept = LocalRows(rows.ids[m], rows.x[m], y[m], rows.clean[m], cfg.gamma)
        scale = cfg.but(lam=cfg.lam * 300 / 299)
        out.append(300 * (quality(core.trusted_local(x, t, w.shape[0]), core.train_newton(kept, scale))["loss"] - base))
    assert np.corrcoef(effect[::30], out)[0, 1] > 0.99


def test_gamma_one_needs_no_bracket_width(setting):
    _, rows, w, v, *_ = setting
    p0 = core.softmax(rows.x @ (w * 0.9).T)
    h = core.hessian_norms(rows.x, p0)
    centre, low, high = pruner.bracket(rows.x @ v.T, rows.y, p0, h, 1.0, pruner.drift(v, w, w * 0.9), "softmax_exact")
    assert centre == pytest.approx(influence.uplift_scores(rows.x, rows.y, w, v, 1.0)) and (low == high).all()


@pytest.mark.parametrize("kind", ["printed", "half", "softmax_exact"])
def test_brackets_with_the_ceiling_hold_always(setting, kind):
    cfg, rows, w, v, *_ = setting
    w0 = w + np.random.default_rng(7).normal(size=w.shape) * 0.3
    exact = influence.uplift_scores(rows.x, rows.y, w, v, cfg.gamma)
    centre, low, high = pruner.bracket(rows.x @ v.T, rows.y, core.softmax(rows.x @ w0.T), (rows.x**2).sum(axis=1) / 2, cfg.gamma, pruner.drift(v, w, w0), kind)
    assert ((low <= exact + 1e-9) & (exact <= high + 1e-9)).all()


def test_empty_edit_replays_the_cached_path(setting):
    cfg, rows, *_ = setting
    w, trace = core.train_sgd(rows, cfg)
    again, new, explicit = replay.replay(rows, trace, replay.Edits.none(3, 6), replay.Edits.none(3, 6), cfg)
    assert (again == w).all() and explicit == 0 and len(new) == len(trace)


@pytest.mark.parametrize("batches", [1, 3])
def test_replay_is_close_to_retraining_and_useless_without_curvature(setting, batches):
    cfg = setting[0].but(batches=batches, steps=90)
    rows, truth = setting[1], setting[6]
    before, trace = core.train_sgd(rows, cfg)
    ids = np.arange(0, 300, 30)
    new = np.eye(3)[truth[ids]]
    w, _, explicit = replay.replay_label_edits(rows, trace, ids, rows.x[ids], rows.y[ids], new, cfg)
    y, clean = rows.y.copy(), rows.clean.copy()
    y[ids], clean[ids] = new, True
    full, _ = core.train_sgd(LocalRows(rows.ids, rows.x, y, clean, cfg.gamma), cfg)
    bare, _, _ = replay.replay_label_edits(rows, trace, ids, rows.x[ids], rows.y[ids], new, cfg, curvature="none")
    good, bad = replay.closeness(w, full, before, rows), replay.closeness(bare, full, before, rows)
    assert good["rel_move"] < (0.05 if batches == 1 else 0.6) and good["agree"] > 0.97 and bad["rel_move"] > 3 * good["rel_move"]
    assert explicit < cfg.steps / 2


def test_all_steps_explicit_is_retraining(setting):
    cfg = setting[0].but(batches=3, steps=30, burn_in=30)
    rows, truth = setting[1], setting[6]
    _, trace = core.train_sgd(rows, cfg)
    ids = np.arange(5)
    new = np.eye(3)[truth[ids]]
    w, _, _ = replay.replay_label_edits(rows, trace, ids, rows.x[ids], rows.y[ids], new, cfg)
    y, clean = rows.y.copy(), rows.clean.copy()
    y[ids], clean[ids] = new, True
    assert w == pytest.approx(core.train_sgd(LocalRows(rows.ids, rows.x, y, clean, cfg.gamma), cfg)[0], abs=1e-12)


def test_curvature_memory_meets_the_secant_condition():
    h = np.diag([1.0, 3.0, 7.0])
    m = replay.CurvatureMemory(2)
    for s in (np.array([1.0, 0.2, 0.0]), np.array([0.1, 1.0, 0.4])):
        m.add(s, h @ s)
    assert m.apply(s) == pytest.approx(h @ s)
    m.add(np.ones(3), -np.ones(3))
    assert len(m.s) == 2
    assert (replay.CurvatureMemory(2).apply(s) == 0).all()


def test_f1_and_simplex():
    from tidelabel.operators.baselines import to_simplex

    assert f1(np.array([1, 1, 0]), np.array([1, 0, 0]), 2) == pytest.approx(2 / 3)
    out = to_simplex(np.array([[2.0, -1.0, 0.0], [0.2, 0.3, 0.5]]))
    assert out.sum(axis=1) == pytest.approx([1, 1]) and out[0] == pytest.approx([1, 0, 0]) and out[1] == pytest.approx([0.2, 0.3, 0.5])
