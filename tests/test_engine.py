"""The engine on small tables."""

import uuid

import numpy as np
import pytest
from pyspark.sql import functions as F

from tidelabel.config import CleanConfig
from tidelabel.operators import annotate, influence, pruner
from tidelabel.operators.core import ClusterRows, gradient, hessian, influence_vector, objective, rows_of, train_newton, train_sgd, trusted_rows, validation_gradient
from tidelabel.operators.measures import confusions, f1, f1_of, same_picks
from tidelabel.operators.measures import quality as quality_of
from tidelabel.operators.replay import retrain, warm_refit
from tidelabel.plans.loop import initialise, on_cluster, resume, run_loop, save
from tidelabel.sources.tables import checked, doc_quality, training_set, vec_planted


@pytest.fixture(scope="module")
def quality(spark):
    return doc_quality(spark, "/root/testdata/sf0.01").persist()


CFG = CleanConfig(budget=15, round_size=5, steps=40)


def test_cluster_sums_equal_local_ones(quality):
    local, far = rows_of(quality, CFG), ClusterRows(quality.where("split = 'train'"), CFG.gamma)
    w = np.full(local.shape, 0.1)
    w[1] = -0.2
    assert far.size == local.size and far.shape == local.shape
    assert objective(far, w, 0.1) == pytest.approx(objective(local, w, 0.1))
    assert gradient(far, w, 0.1, (2, 1, 3))[0] == pytest.approx(gradient(local, w, 0.1, (2, 1, 3))[0])
    assert hessian(far, w, 0.1) == pytest.approx(hessian(local, w, 0.1))


def test_trusted_rows_of_the_cluster_equal_those_of_the_driver(quality):
    local, far = trusted_rows(quality, "val", CFG), trusted_rows(quality, "val", CFG.but(local_bytes=0))
    assert isinstance(far, ClusterRows) and far.size == local.size > 0
    w = np.full(far.shape, 0.1)
    w[1] = -0.2
    assert validation_gradient(far, w) == pytest.approx(validation_gradient(local, w))
    assert quality_of(far, w) == pytest.approx(quality_of(local, w)) and (confusions(far, w)[1] == confusions(local, w)[1]).all()
    assert f1_of(confusions(local, w)[1]) == pytest.approx(f1(local.truth, (local.x @ w.T).argmax(axis=1), 2))
    assert quality_of(trusted_rows(quality, "none", CFG), w) == {"loss": 0.0, "f1": 0.0}


def test_the_loop_runs_on_the_cluster_alone(quality):
    """Nothing held by the driver: the same picks and losses, up to rounding."""
    few = CFG.but(budget=4, round_size=2, steps=6, burn_in=2, period=4)
    local, far = run_loop(quality, few), run_loop(quality, few.but(local_bytes=0))
    assert isinstance(far.rows, ClusterRows) and isinstance(far.val, ClusterRows)
    assert far.edits == local.edits and far.w == pytest.approx(local.w)
    assert [r["val_loss"] for r in far.log] == pytest.approx([r["val_loss"] for r in local.log])


def test_rounds_go_on_from_a_saved_state(quality, tmp_path):
    half = run_loop(quality, CFG.but(budget=10), prune=True)
    save(half, str(tmp_path))
    again = resume(quality, CFG, str(tmp_path), prune=True)
    assert again.edits == half.edits and (again.w == half.w).all() and len(again.trace) == len(half.trace)
    whole, resumed = run_loop(quality, CFG, prune=True), run_loop(quality, CFG, prune=True, start=again)
    assert resumed.edits == whole.edits and resumed.w == pytest.approx(whole.w)
    assert resumed.log[-1]["n_candidates"] == whole.log[-1]["n_candidates"]


def test_warm_refit_comes_close_in_few_steps(quality):
    rows = rows_of(quality, CFG)
    w, _ = train_sgd(rows, CFG.but(steps=400))
    rows.clean[:15] = True
    full, _ = retrain(rows, CFG.but(steps=400))
    warm, trace = warm_refit(rows, CFG, w, 40)
    assert len(trace) == 40 and np.abs(warm - full).max() < 0.3 * np.abs(w - full).max()


def test_training_ends_early_where_the_validation_loss_rises(quality):
    overfit = CFG.but(steps=60, patience=2)
    losses = iter(range(100))
    _, trace = train_sgd(rows_of(quality, CFG), overfit, stop=lambda w: next(losses), patience=2)
    assert len(trace) == 3 and len(initialise(quality, overfit).trace) <= 60


def test_loop_lowers_validation_loss_more_than_random(quality):
    ours, random = run_loop(quality, CFG, prune=True), run_loop(quality, CFG, "random", "retrain")
    losses = [r["val_loss"] for r in ours.log]
    assert losses == sorted(losses, reverse=True) and losses[-1] < random.log[-1]["val_loss"]
    assert ours.log[-1]["n_cleaned"] == 15 and sum(r["agreed"] for r in ours.log) >= 12
    assert all(r["n_candidates"] < r["n_pool"] for r in ours.log[2:])
    assert ours.train.count() == quality.count() and ours.train.where("is_clean").count() == 15


def test_loop_stops_when_told_and_when_the_pool_is_empty(spark, quality):
    assert len(run_loop(quality, CFG, stop=lambda r: r["round"] >= 1).log) == 2
    few = quality.where("split <> 'train' or row_id % 40 = 0")
    n = few.where("split = 'train'").count()
    assert run_loop(few, CFG.but(budget=1000, round_size=n), update="retrain").log[-1]["n_cleaned"] == n


@pytest.mark.parametrize("kind", ["printed", "half", "softmax_exact"])
def test_pruner_picks_what_full_scoring_picks(quality, kind):
    s = initialise(quality, CFG, prune=True)
    w = train_newton(s.rows, CFG)
    v = influence_vector(s.rows, validation_gradient(s.val, w), w, CFG)
    full = influence.select_top(influence.uplift_influence(quality, w, v, CFG.gamma), 10)
    for bounds in (pruner.brackets(s.prov, v, w, s.w0, CFG.gamma, kind), pruner.prescreen(s.prov, v, s.v0, w, s.w0, CFG.gamma)):
        for threshold in ("printed", "tight"):
            diff = same_picks(full, pruner.pruned_top(bounds, w, v, CFG.gamma, 10, threshold)[0]).first()
            assert (diff.only_a, diff.only_b) == (0, 0)
    exact = influence.uplift_influence(quality, w, v, CFG.gamma)
    assert pruner.violations(pruner.prescreen(s.prov, v, s.v0, w, s.w0, CFG.gamma), exact) == 0


def test_ties_go_to_the_smaller_id(spark):
    rows = spark.createDataFrame([(i, [1.0, 1.0], [0.5, 0.5], "train", False) for i in (9, 3, 5)], "row_id long, x array<double>, weak array<double>, split string, is_clean boolean")
    w, v = np.zeros((2, 2)), np.array([[1.0, 0], [-1.0, 0]])
    assert [r.row_id for r in influence.select_top(influence.uplift_influence(rows, w, v, 0.8), 2).collect()] == [3, 5]


def test_majority_ties(spark):
    votes = spark.createDataFrame([(1, "a", 2), (1, "b", 1), (1, "c", 0), (2, "a", 1), (2, "b", 1), (2, "c", 0)], "row_id long, annotator string, label int")
    best = lambda **k: {r.row_id: r.label for r in annotate.majority_vote(votes, **k).collect()}
    assert best() == {1: 0, 2: 1} and best(tie="keep") == {2: 1}
    assert best(tie="suggested", suggestions=spark.createDataFrame([(1, 2)], "row_id long, best_class int")) == {1: 2, 2: 1}


def test_bad_weak_labels_are_refused(spark):
    for weak in ([0.5, 0.6], [float("nan"), 1.0], [1.0], [-0.5, 1.5]):
        rows = spark.createDataFrame([(1, [1.0], 0, weak)], "row_id long, x array<double>, truth int, w array<double>")
        with pytest.raises(ValueError):
            checked(training_set(rows, 2, F.col("w")), 2)
    with pytest.raises(ValueError):
        CleanConfig(gamma=0)


def test_weak_labels_sum_to_one(spark, sf_dir):
    worst = vec_planted(spark, sf_dir).agg(F.max(F.abs(F.aggregate("weak", F.lit(0.0), lambda a, b: a + b) - 1)).alias("m")).first().m
    assert worst < 1e-9


def test_late_rows_are_dropped_from_windows(spark, tmp_path):
    """Micro-batches of one file each: a row behind the watermark of the batch before opens no window, the last window stays open."""
    from tidelabel.schema import TABLES
    from tidelabel.streaming.votes import run_once, tumbling

    day = 86_400
    for i, days in enumerate([(10, 13), (13,), (1, 13), (20,)]):
        rows = [(100 * i + j, d * day + 3600, 1, "click") for j, d in enumerate(days)]
        events = spark.createDataFrame(rows, "event_id long, t long, user_id long, event_type string").select("event_id", F.timestamp_seconds("t").alias("ts"), "user_id", "event_type", F.lit(0.0).alias("value"), F.lit("{}").alias("props"))
        events.coalesce(1).write.mode("append").parquet(f"{tmp_path}/events")
    stream = spark.readStream.schema(TABLES["events"]).option("maxFilesPerTrigger", 1).parquet(f"{tmp_path}/events")
    got = {(r.start.day, r.n) for r in run_once(tumbling(stream)).collect()}
    assert got == {(11, 1), (14, 3)}


def test_annotators_with_commas_are_one_vote_each(spark, tmp_path):
    from tidelabel.streaming.votes import quorum, run_once

    votes = spark.createDataFrame([(1, "a,b", 1, 1), (1, "c", 0, 2), (1, "c", 1, 3), (1, "d,", 0, 4)], "row_id long, annotator string, label int, t int").withColumn("ts", F.timestamp_seconds("t")).drop("t")
    votes.coalesce(1).write.parquet(f"{tmp_path}/votes")
    stream = spark.readStream.schema(votes.schema).parquet(f"{tmp_path}/votes")
    assert [tuple(r) for r in run_once(quorum(stream)).select("row_id", "label", "n").collect()] == [(1, 0, 3)]


def test_votes_beyond_the_quorum_do_not_count(spark):
    from tidelabel.streaming.votes import quorum_batch

    votes = spark.createDataFrame([(1, "a", 1, 1), (1, "a", 0, 2), (1, "b", 0, 3), (1, "c", 0, 4), (1, "d", 1, 5), (2, "a", 1, 1)], "row_id long, annotator string, label int, t int").withColumn("ts", F.timestamp_seconds("t"))
    assert {(r.row_id, r.label, r.n) for r in quorum_batch(votes).collect()} == {(1, 0, 3), (2, 1, 1)}


def jobs_of(spark, action) -> tuple:
    """What ``action`` gives, and the number of Spark jobs that it ran."""
    group = f"counted-{id(action)}"
    spark.sparkContext.setJobGroup(group, group)
    try:
        return action(), len(spark.sparkContext.statusTracker().getJobIdsForGroup(group))
    finally:
        spark.sparkContext.setJobGroup("tests", "tests")


def test_a_path_over_mini_batches_on_the_cluster_takes_a_few_jobs(spark, quality):
    """A job a step took the large order-line workloads hours; edits are seen without dealing out again."""
    small = CFG.but(batches=12, steps=24, burn_in=3, period=5)
    local, far = rows_of(quality, small), rows_of(quality, small.but(local_bytes=0))
    (w, trace), n = jobs_of(spark, lambda: train_sgd(far, small))
    want, path = train_sgd(local, small)
    assert w == pytest.approx(want) and [s.n for s in trace] == [s.n for s in path] and n < 12
    begin = initialise(quality, small.but(local_bytes=0))
    a, b = (run_loop(quality, small.but(budget=4, round_size=2, local_bytes=k), update=u) for k, u in ((64 << 20, "replay"), (0, "replay")))
    assert b.edits == a.edits and b.w == pytest.approx(a.w) and isinstance(begin.rows, ClusterRows)
    again, plain = retrain(b.rows, small)[0], retrain(a.rows, small)[0]
    assert again == pytest.approx(plain) and again != pytest.approx(want)


@pytest.mark.parametrize("held", [64 << 20, 0])
def test_selection_by_blocks_equals_that_by_rows(spark, quality, held):
    """Brackets of all rows went back to Spark as lists, which took most of a round's selection."""
    cfg = CFG.but(local_bytes=held)
    s = initialise(quality, cfg, prune=True)
    w = s.w0 * 0.97
    v = influence_vector(s.rows, validation_gradient(s.val, w), w, cfg)
    done = [r.row_id for r in influence.select_top(influence.uplift_influence(quality, w, v, cfg.gamma), 3).collect()]
    full = influence.select_top(influence.uplift_influence(on_cluster(s), w, v, cfg.gamma, 10), 10).collect()
    assert [r.row_id for r in full] == [r.row_id for r in influence.select_top(influence.uplift_influence(quality, w, v, cfg.gamma), 10).collect()]
    pairs = [(pruner.brackets(s.prov, v, w, s.w0, cfg.gamma, k, m, done), pruner.bracket_reach(v, w, s.w0, cfg.gamma, k, m)) for k in ("printed", "softmax_exact") for m in ("anchor", "ceiling")]
    for bounds, reach in [*pairs, (pruner.prescreen(s.prov, v, s.v0, w, s.w0, cfg.gamma, done), pruner.prescreen_reach(v, s.v0, w, s.w0, cfg.gamma))]:
        for threshold in ("printed", "tight"):
            best, n, _ = pruner.pruned_top(bounds, w, v, cfg.gamma, 10, threshold)
            # a group of its own name: that of jobs_of may come again, as a freed lambda's id does
            group = f"selection-{uuid.uuid4().hex}"
            spark.sparkContext.setJobGroup(group, group)
            got, m, _ = pruner.pruned_rows(s.facts, reach, w, v, cfg.gamma, 10, threshold, done)
            jobs = len(spark.sparkContext.statusTracker().getJobIdsForGroup(group))
            spark.sparkContext.setJobGroup("tests", "tests")
            want = best.orderBy("best_score", "row_id").collect()
            assert m == n and [(r.row_id, r.best_class) for r in got] == [(r.row_id, r.best_class) for r in want] and [r.best_score for r in got] == pytest.approx([r.best_score for r in want])
            assert jobs <= 2 and not {r.row_id for r in got} & set(done)
    assert pruner.pruned_rows(s.facts, reach, w, v, cfg.gamma, 10, done=[r.row_id for r in quality.select("row_id").collect()])[:2] == ([], 0)


def test_mini_batches_come_while_steps_are_made(spark, quality, monkeypatch):
    """Each fetch waited for the steps before it; edits made before dealing must not be dealt out."""
    from tidelabel.operators import core

    monkeypatch.setattr(core, "FETCH_BYTES", 30_000)
    small = CFG.but(batches=12, steps=24)
    local, far, asked = rows_of(quality, small), rows_of(quality, small.but(local_bytes=0)), []
    ids, new = local.ids[:3], np.eye(2)[[0, 0, 0]]
    edited = far.edited(quality, ids, new)
    fetch = ClusterRows.fetched
    monkeypatch.setattr(ClusterRows, "fetched", lambda self, part: asked.append(part[0]) or fetch(self, part))
    keys = [(*divmod(t, 12), 12) for t in range(24)]
    coming = edited.each_batch(keys)
    first = next(coming)
    assert len(asked) >= 2
    sums = lambda x, y, g: np.append((x.T @ y).ravel(), g.sum())
    y, clean = local.y.copy(), local.clean.copy()
    y[:3], clean[:3] = new, True
    for rows, parts in ((core.LocalRows(local.ids, local.x, y, clean, local.gamma), [first, *coming]), (local, list(far.each_batch(keys)))):
        for k, part in zip(keys, parts, strict=True):
            want, n = rows.total(sums, k)
            got, m = part.total(sums)
            assert m == n and got == pytest.approx(want)


def test_votes_of_few_rows_equal_those_of_the_table(spark, quality):
    truth = {r.row_id: r.truth for r in quality.where("split = 'train'").limit(60).collect()}
    picks = {i: i % 2 for i in truth}
    frame = spark.createDataFrame(list(picks.items()), "row_id long, best_class int")
    given = spark.createDataFrame([(i, f"v{k}", int((i + k) % 3 > 0)) for i in truth for k in range(4)], "row_id long, annotator string, label int")
    for strategy in ("HUMAN3", "SUGGEST", "MIX"):
        for votes in (None, given):
            want = {r.row_id: r.new_label for r in annotate.clean_labels(frame, strategy, quality, 2, 0.2, votes).collect()}
            assert annotate.clean_few(picks, strategy, truth, 2, 0.2, None if votes is None else [(r.row_id, r.label) for r in votes.collect()]) == want


def test_the_drivers_random_order_is_the_tables(quality):
    from tidelabel.operators.baselines import random_order

    want = [r.row_id for r in influence.select_top(random_order(quality), 20).collect()]
    assert [r.row_id for r in random_order(rows_of(quality, CFG)).top(20)] == want


def test_the_crowd_is_asked_in_one_job_a_round(spark, sf_dir):
    from tidelabel.queries import experiments

    rows, n = jobs_of(spark, lambda: experiments.QUERIES["exp1_crowd"](spark, sf_dir))
    rounds = sum(-(-r.n_cleaned // r.b) for r in rows.collect() if r.strategy == "HUMAN3" or r.strategy == "MIX")
    assert n < rounds + 40
