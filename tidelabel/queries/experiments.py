"""Experiment workloads: label quality, selection time, update time, sweeps. Results of loops, so without SQL twins."""

from __future__ import annotations

import time

import numpy as np
from pyspark.sql import functions as F

from tidelabel.config import CleanConfig
from tidelabel.functions.rand import random_weak
from tidelabel.operators import baselines, influence, pruner
from tidelabel.operators.core import influence_vector, rows_of, train_newton, trusted_rows, validation_gradient
from tidelabel.operators.measures import mean_and_spread, quality
from tidelabel.operators.replay import closeness, replay_label_edits, retrain, warm_refit
from tidelabel.plans.loop import choose, edited_rows, initialise, on_cluster, picked_rows, run_loop
from tidelabel.schema import ROUNDS
from tidelabel.sources.sinks import written
from tidelabel.sources.tables import FIXTURES, checked, crowd_votes, doc_crowd, document_statistics

QUERIES = {}


def query(name: str):
    return lambda fn: QUERIES.setdefault(name, fn)


def settings(train, classes: int = 2, **more) -> CleanConfig:
    """Budgets and batches by the training set's rows: a tenth of them, at most 100, in ten rounds; 2,000 rows a batch."""
    n = train.where("split = 'train'").count()
    budget, batches = max(1, min(100, n // 10)), max(1, round(n / 2000))
    return CleanConfig(classes=classes, budget=budget, round_size=max(1, budget // 10), batches=batches, steps=max(60, 2 * batches), lam=0.05 if classes == 2 else 0.01).but(**more)


def fixture(spark, sf_dir, name):
    make, classes = FIXTURES[name]
    return checked(make(spark, sf_dir).persist(), classes), classes


def as_rounds(spark, state):
    names = [c.split()[0] for c in ROUNDS.split(", ")]
    return spark.createDataFrame([tuple(r[c] for c in names) for r in state.log], ROUNDS)


@query("loop_rounds")
def _(spark, sf_dir):
    train, _ = fixture(spark, sf_dir, "doc_quality")
    return as_rounds(spark, run_loop(train, settings(train), prune=True))


@query("loop_oneshot")
def _(spark, sf_dir):
    train, _ = fixture(spark, sf_dir, "doc_quality")
    cfg = settings(train)
    return as_rounds(spark, run_loop(train, cfg.but(round_size=cfg.budget), update="retrain"))


@query("loop_target")
def _(spark, sf_dir):
    """Rounds until the validation loss has fallen by a fifth, and the labels bought until then."""
    train, _ = fixture(spark, sf_dir, "doc_quality")
    cfg = settings(train, strategy="MIX")
    state = initialise(train, cfg)
    first = run_loop(train, cfg, start=state, stop=lambda r: True).log[0]["val_loss"]
    return as_rounds(spark, run_loop(train, cfg, start=state, stop=lambda r: r["val_loss"] <= 0.8 * first))


STRATEGIES = (("uplift", "HUMAN3"), ("uplift", "SUGGEST"), ("uplift", "MIX"))
OTHERS = tuple((m, "HUMAN3") for m in ("deletion", "label_gradient", "least_confidence", "entropy", "detector_a", "random"))
COMPARED = "method string, strategy string, b int, refresh string, n_cleaned int, loss_before double, loss_after double, f1_before double, f1_after double, agreed int, votes int"


def arms(cfg, methods=STRATEGIES + OTHERS):
    """Every method at both round sizes, retrained; and suggestions in rounds with replay."""
    both = [(m, s, b, "retrain") for b in dict.fromkeys((cfg.budget, cfg.round_size)) for m, s in methods]
    return both + [("uplift", "SUGGEST", cfg.round_size, "replay")] * (("uplift", "SUGGEST") in methods)


def compared(spark, train, cfg, plan, votes=None):
    state, rows = initialise(train, cfg), []
    for method, strategy, b, update in plan:
        s = run_loop(train, cfg.but(strategy=strategy, round_size=b), method, update, start=state, votes=votes)
        last = s.log[-1]
        agreed = sum(r["agreed"] for r in s.log) if votes is None else None
        rows.append((method, strategy, b, update, last["n_cleaned"], s.log[0]["val_loss"], last["val_loss"], s.log[0]["test_f1"], last["test_f1"], agreed, sum(r["votes"] for r in s.log)))
    train.unpersist()
    return spark.createDataFrame(rows, COMPARED)


def whole(spark, sf_dir, name):
    train, classes = fixture(spark, sf_dir, name)
    cfg = settings(train, classes)
    return compared(spark, train, cfg, arms(cfg))


for _name, _fixture in (("exp1_quality", "doc_quality"), ("exp1_toxic", "doc_toxic"), ("exp1_planted4", "vec_planted4"), ("exp1_role", "conv_role"), ("exp1_control", "vec_control")):
    QUERIES[_name] = lambda spark, sf_dir, f=_fixture: whole(spark, sf_dir, f)


REPEATS = 3


@query("exp1_spread")
def spread(spark, sf_dir, names=("doc_quality", "doc_toxic"), repeats: int = REPEATS):
    """Mean and spread over ``repeats`` draws of random weak labels, in rounds."""
    out = []
    for name in names:
        train, classes = fixture(spark, sf_dir, name)
        cfg, found = settings(train, classes), {}
        for k in range(repeats):
            drawn = train.withColumn("weak", F.when(F.col("split") == "train", random_weak(f"weak-{k}", "row_id", classes)).otherwise(F.col("weak"))).persist()
            for r in compared(spark, drawn, cfg, [(m, s, cfg.round_size, "retrain") for m, s in (("uplift", "SUGGEST"), ("deletion", "HUMAN3"), ("least_confidence", "HUMAN3"), ("random", "HUMAN3"))]).collect():
                found.setdefault(r.method, []).append((r.loss_after, r.f1_after))
        for method, values in found.items():
            (loss, loss_spread), (f1, f1_spread) = (mean_and_spread(list(v)) for v in zip(*values))
            out.append((name, method, repeats, loss, loss_spread, f1, f1_spread))
        train.unpersist()
    return spark.createDataFrame(out, "workload string, method string, repeats int, loss_mean double, loss_spread double, f1_mean double, f1_spread double")


@query("exp1_crowd")
def _(spark, sf_dir):
    """Documents without a label: the four labelling functions are the crowd whose votes are bought; no truth to agree with."""
    # texts are read once, for features and votes; every round asks for a few rows' votes
    stats = written(document_statistics(spark, sf_dir), "statistics")
    train = checked(doc_crowd(spark, sf_dir, stats).persist(), 2)
    cfg = settings(train)
    return compared(spark, train, cfg, arms(cfg), written(crowd_votes(spark, sf_dir, stats), "votes"))


@query("exp1_hard")
def _(spark, sf_dir):
    """Hard labels, for which the second detector is made: it and uplift side by side."""
    train, classes = fixture(spark, sf_dir, "doc_quality")
    top = F.array_position("weak", F.array_max("weak")) - 1
    hard = train.withColumn("weak", F.transform(F.sequence(F.lit(0), F.lit(classes - 1)), lambda c: (c == top).cast("double"))).persist()
    cfg = settings(hard)
    out = compared(spark, hard, cfg, [(m, "SUGGEST", b, "retrain") for b in dict.fromkeys((cfg.budget, cfg.round_size)) for m in ("uplift", "detector_b")])
    train.unpersist()
    return out


@query("exp1_agreement")
def _(spark, sf_dir):
    """Suggestions equal to the truth, of all rows cleaned in rounds."""
    out = []
    for name in ("doc_quality", "doc_toxic", "vec_planted4"):
        train, classes = fixture(spark, sf_dir, name)
        cfg = settings(train, classes)
        out += [(name, r.agreed, r.n_cleaned) for r in compared(spark, train, cfg, [("uplift", "SUGGEST", cfg.round_size, "retrain")]).collect()]
    return spark.createDataFrame(out, "workload string, agreed int, n_cleaned int")


@query("exp1_bilevel")
def _(spark, sf_dir):
    """Bi-level and uplift, once for the whole budget, at gamma 1."""
    train, _ = fixture(spark, sf_dir, "doc_quality")
    cfg = settings(train, gamma=1.0)
    rows, val = rows_of(train, cfg), trusted_rows(train, "val", cfg)
    moved, suggested = baselines.bilevel(rows, val, cfg)
    first = np.lexsort((rows.ids, -moved))[: cfg.budget]
    s = spark.createDataFrame([(int(rows.ids[i]), int(suggested[i])) for i in first], "row_id long, best_class int")
    state = initialise(train, cfg)
    v = influence_vector(rows, validation_gradient(val, state.w), state.w, cfg)
    u = influence.select_top(influence.uplift_influence(train, state.w, v, 1.0), cfg.budget).select("row_id", "best_class")
    right = lambda p, n: p.join(train.select("row_id", "truth"), "row_id").agg(F.lit(n).alias("method"), F.sum((F.col("truth") == F.col("best_class")).cast("int")).alias("agreed"), F.count("*").alias("n"))
    return right(s, "bilevel").union(right(u, "uplift"))


QUERIES["bilevel_topb"] = QUERIES["exp1_bilevel"]


@query("detector_a")
def _(spark, sf_dir):
    train, _ = fixture(spark, sf_dir, "doc_quality")
    cfg = settings(train)
    rows = rows_of(train, cfg)
    return influence.select_top(baselines.detector_a(train, rows, train_newton(rows, cfg), cfg), cfg.budget).selectExpr("row_id as doc_id", "round(best_score, 9) as score")


@query("detector_b")
def _(spark, sf_dir):
    train, _ = fixture(spark, sf_dir, "doc_quality")
    cfg = settings(train)
    rows, val = rows_of(train, cfg), trusted_rows(train, "val", cfg)
    w = train_newton(rows, cfg)
    v = influence_vector(rows, validation_gradient(val, w), w, cfg)
    return influence.select_top(baselines.detector_b(train, val, w, v), cfg.budget).selectExpr("row_id as doc_id", "best_class", "round(best_score, 9) as score")


def swept(spark, sf_dir, values, change, names=("doc_quality",)):
    rows = []
    for name in names:
        train, classes = fixture(spark, sf_dir, name)
        cfg = settings(train, classes)
        for v in values:
            began = time.perf_counter()
            s = run_loop(train, change(cfg, v), update="replay", prune=True)
            rows.append((name, float(v), s.log[-1]["val_loss"], s.log[-1]["test_f1"], s.log[-1]["round"], s.log[-1]["n_cleaned"], time.perf_counter() - began))
        train.unpersist()
    return spark.createDataFrame(rows, "workload string, value double, val_loss double, test_f1 double, rounds int, n_cleaned int, seconds double")


QUERIES["sweep_b"] = lambda spark, sf_dir: swept(spark, sf_dir, (5, 10, 20, 50, 100), lambda c, v: c.but(round_size=min(v, c.budget)))
QUERIES["sweep_gamma"] = lambda spark, sf_dir: swept(spark, sf_dir, (0.2, 0.5, 0.8, 1.0), lambda c, v: c.but(gamma=v), ("doc_quality", "vec_planted4"))


@query("exp0_rounds")
def _(spark, sf_dir):
    """The same budget in one batch and in ten rounds."""
    return swept(spark, sf_dir, (1, 10), lambda c, v: c.but(round_size=max(1, c.budget // v)))


@query("exp2_select")
def _(spark, sf_dir):
    """Selection in every cleaning round after the first by full scoring, the pruner and the prescreen; ``last`` marks the result."""
    out = []
    for name in ("line_planted", "doc_quality", "vec_planted4"):
        train, classes = fixture(spark, sf_dir, name)
        cfg = settings(train, classes)
        state, rows = initialise(train, cfg, prune=True), []

        def measure(now, _, name=name, state=state, cfg=cfg, rows=rows):
            if not now.edits:
                return
            v, n_pool, picks = now.v, now.rows.size - len(now.edits), {}
            for method in ("full", "pruner", "prescreen"):
                began = time.perf_counter()
                if method == "full":
                    top, n = influence.select_top(influence.uplift_influence(on_cluster(now), now.w, v, cfg.gamma, cfg.round_size), cfg.round_size).collect(), n_pool
                    t_grad = time.perf_counter() - began
                else:
                    reach = pruner.bracket_reach(v, now.w, state.w0, cfg.gamma, cfg.brackets) if method == "pruner" else pruner.prescreen_reach(v, state.v0, now.w, state.w0, cfg.gamma)
                    top, n, t_grad = pruner.pruned_rows(state.facts, reach, now.w, v, cfg.gamma, cfg.round_size, cfg.threshold, now.edits)
                picks[method] = {r.row_id for r in top}
                rows.append((name, len(now.log), method, n, n_pool, time.perf_counter() - began, t_grad, picks[method] == picks["full"]))

        run_loop(train, cfg, start=state, each=measure)
        last = max((r[1] for r in rows), default=0)
        out += [(*r, r[1] == last) for r in rows]
        train.unpersist()
    return spark.createDataFrame(out, "workload string, round int, method string, n_candidates long, n_pool long, t_inf double, t_grad double, same_picks boolean, last boolean")


UPDATES = "workload string, round int, method string, explicit_steps int, seconds double, rel_err double, agree double, val_loss double, test_f1 double"


@query("exp3_update")
def _(spark, sf_dir):
    """Refreshing by replay, by replay without curvature and by retraining, in every cleaning round; each round goes on from the replay."""
    out = []
    for name in ("line_planted", "doc_quality"):
        train, classes = fixture(spark, sf_dir, name)
        cfg = settings(train, classes)
        state = initialise(train, cfg)
        for k in range(1, -(-cfg.budget // cfg.round_size) + 1):
            picks, _ = choose(state, cfg, min(cfg.round_size, cfg.budget - len(state.edits)))
            out += [(name, k, *r) for r in refreshed(state, picks, cfg)]
        train.unpersist()
    return spark.createDataFrame(out, UPDATES)


@query("replay_round")
def _(spark, sf_dir):
    """One round's refresh with full batches."""
    train, _ = fixture(spark, sf_dir, "doc_quality")
    cfg = settings(train, steps=150, batches=1)
    state = initialise(train, cfg)
    return spark.createDataFrame([("doc_quality", 1, *r) for r in refreshed(state, choose(state, cfg, cfg.round_size)[0], cfg)], UPDATES)


def refreshed(state, picks, cfg):
    """A row for each way to refresh after the suggested labels of ``picks``; the state goes on with the replay's model."""
    chosen = {r.row_id: r.best_class for r in picks}
    ids, x, old, _ = picked_rows(state, list(chosen))
    new = np.eye(cfg.classes)[[chosen[i] for i in ids]]
    before = state.w
    state.edits, state.seen = state.edits | chosen, None
    edited = edited_rows(state, ids, new, cfg)
    ways = {
        "replay": lambda: replay_label_edits(state.rows, state.trace, ids, x, old, new, cfg), "retrain": lambda: (*retrain(edited, cfg), len(state.trace)),
        "warm": lambda: (*warm_refit(edited, cfg, before, cfg.warm_steps), cfg.warm_steps),
        "replay without curvature": lambda: replay_label_edits(state.rows, state.trace, ids, x, old, new, cfg, curvature="none"),
    }
    done = {}
    for method, refresh in ways.items():
        t0 = time.perf_counter()
        done[method] = (*refresh(), time.perf_counter() - t0)
    full, out = done["retrain"][0], []
    for method, (w, _, explicit, took) in done.items():
        c, val, test = closeness(w, full, before, state.test), quality(state.val, w), quality(state.test, w)
        out.append((method, explicit, took, c["rel_move"], c["agree"], val["loss"], test["f1"]))
    state.w, state.trace, state.rows = done["replay"][0], done["replay"][1], edited
    return out


@query("exp1_neighbours")
def _(spark, sf_dir):
    """Labels of trusted rows near the first pick."""
    from tidelabel.operators.neighbours import nearest_trusted

    train, classes = fixture(spark, sf_dir, "vec_planted4")
    cfg = settings(train, classes)
    state = initialise(train, cfg)
    v = influence_vector(state.rows, validation_gradient(state.val, state.w), state.w, cfg)
    pick = influence.select_top(influence.uplift_influence(train, state.w, v, cfg.gamma), 1).select("row_id", "best_class")
    near = nearest_trusted(train.join(pick, "row_id").select(F.col("row_id").alias("vec_id"), "x"), train.where("split <> 'train'").select(F.col("row_id").alias("vec_id"), "x"), 5)
    return near.join(train.select(F.col("row_id").alias("nn_id"), "truth"), "nn_id").join(pick.withColumnRenamed("row_id", "vec_id"), "vec_id")


@query("exp1_large")
def _(spark, sf_dir):
    """Up to 2,000 rows, a tenth at most, cleaned at once, by uplift and its rivals."""
    train, _ = fixture(spark, sf_dir, "line_planted")
    cfg = settings(train)
    large = max(1, min(2000, train.where("split = 'train'").count() // 10))
    return compared(spark, train, cfg.but(budget=large, round_size=large), [(m, s, large, "retrain") for m, s in (("uplift", "SUGGEST"), ("uplift", "HUMAN3"), ("deletion", "HUMAN3"), ("label_gradient", "HUMAN3"), ("random", "HUMAN3"))])
