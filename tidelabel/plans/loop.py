"""The cleaning loop: choose rows, get labels, apply them, refresh the model, measure, stop or go on.

Round state (picks, edits, metrics) is small and kept on the driver; the training table
is immutable and seen through the edits so far. Scores and brackets are distributed
passes. With ``b = budget`` the loop is the one-shot one.
"""

from __future__ import annotations

import time
from collections.abc import Callable
from dataclasses import dataclass, field, replace

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from tidelabel.config import CleanConfig
from tidelabel.operators import annotate, baselines, influence, pruner
from tidelabel.operators.core import ClusterRows, LocalRows, Step, influence_vector, packed, rows_of, train_sgd, trusted_rows, validation_gradient
from tidelabel.operators.measures import quality
from tidelabel.operators.replay import replay_label_edits, retrain, warm_refit
from tidelabel.schema import MODEL, TRACE
from tidelabel.sources.sinks import written
from tidelabel.sources.tables import as_arrays

RANKERS = ("uplift", "deletion", "label_gradient", "least_confidence", "entropy", "margin", "random", "detector_a", "detector_b")


@dataclass
class State:
    seen: DataFrame | None  # the edited table; None: not asked for since the last edits
    base: DataFrame
    rows: object
    val: object
    test: object
    w: np.ndarray
    trace: list
    w0: np.ndarray
    v0: np.ndarray
    facts: DataFrame | None = None  # of the pruner, by blocks
    v: np.ndarray | None = None  # the influence vector of the choice in hand
    votes: DataFrame | None = None  # given votes (row_id, annotator, label); else annotators are simulated
    edits: dict[int, int] = field(default_factory=dict)
    log: list[dict] = field(default_factory=list)

    @property
    def prov(self) -> DataFrame | None:
        """The pruner's facts as rows."""
        return None if self.facts is None else pruner.unpacked(self.facts)

    @property
    def train(self) -> DataFrame:
        """The table as edited so far."""
        if self.seen is None:
            # from Arrow the edits are a local relation; from tuples every pass would read them by a job of its own
            edits = self.base.sparkSession.createDataFrame(pa.table({"row_id": pa.array(self.edits.keys(), pa.int64()), "new_label": pa.array(self.edits.values(), pa.int32())}))
            self.seen = annotate.apply_edits(self.base, edits, len(self.w))
        return self.seen


def initialise(train: DataFrame, cfg: CleanConfig, prune: bool = False) -> State:
    """First training with its trace, and the facts that the pruner keeps, which are written once."""
    rows = rows_of(train, cfg)
    val, test = trusted_rows(train, "val", cfg), trusted_rows(train, "test", cfg)
    stop = (lambda w: quality(val, w)["loss"]) if cfg.patience else None
    w, trace = train_sgd(rows, cfg, stop=stop, patience=cfg.patience)
    v = influence_vector(rows, validation_gradient(val, w), w, cfg)
    state = State(train, train, rows, val, test, w, trace, w, v)
    if prune:
        state.facts = written(pruner.facts(on_cluster(state), w, v), "provenance")
    return state


def on_cluster(state: State) -> DataFrame | ClusterRows:
    """The edited training rows for distributed passes: by blocks where they aren't the driver's."""
    return state.train if isinstance(state.rows, LocalRows) else state.rows


def save(state: State, root: str) -> None:
    """The state's path, parameters and pruner facts as Parquet, so that rounds go on after a lost driver."""
    spark, flat = state.train.sparkSession, lambda a: [float(z) for z in np.ravel(a)]
    spark.createDataFrame([(t, flat(s.w), flat(s.g), s.n) for t, s in enumerate(state.trace)], TRACE).coalesce(1).write.mode("overwrite").parquet(f"{root}/trace")
    spark.createDataFrame([(n, flat(getattr(state, n))) for n in ("w", "w0", "v0")], MODEL).coalesce(1).write.mode("overwrite").parquet(f"{root}/model")
    spark.createDataFrame([(int(r), int(c)) for r, c in state.edits.items()], "row_id long, new_label int").coalesce(1).write.mode("overwrite").parquet(f"{root}/edits")
    if state.facts is not None:
        state.prov.write.mode("overwrite").parquet(f"{root}/provenance")


def resume(train: DataFrame, cfg: CleanConfig, root: str, prune: bool = False) -> State:
    """The state that ``save`` wrote, over the same unedited table; nothing is trained again."""
    spark = train.sparkSession
    edits = {r.row_id: r.new_label for r in spark.read.schema("row_id long, new_label int").parquet(f"{root}/edits").collect()}
    now = annotate.apply_edits(train, spark.createDataFrame(list(edits.items()), "row_id long, new_label int"), cfg.classes) if edits else train
    rows = rows_of(now, cfg)
    m = {r.name: np.reshape(r.value, rows.shape) for r in spark.read.schema(MODEL).parquet(f"{root}/model").collect()}
    trace = [Step(np.reshape(r.w, rows.shape), np.reshape(r.g, rows.shape), r.n_batch) for r in spark.read.schema(TRACE).parquet(f"{root}/trace").orderBy("t").collect()]
    facts = written(packed(spark.read.schema(pruner.PROVENANCE).parquet(f"{root}/provenance")), "provenance") if prune else None
    return State(now, train, rows, trusted_rows(train, "val", cfg), trusted_rows(train, "test", cfg), m["w"], trace, m["w0"], m["v0"], facts, edits=edits)


def scores_by(state: State, method: str, v: np.ndarray, cfg: CleanConfig, b: int | None = None) -> DataFrame:
    # rows that the driver holds are scored there
    t, w = state.train if method == "random" and not isinstance(state.rows, LocalRows) else state.rows, state.w
    if method == "uplift":
        return influence.uplift_influence(t, w, v, cfg.gamma, b)
    if method == "deletion":
        # most harmful first: rows whose removal would lower the validation loss most
        return influence.deletion_influence(t, w, v, cfg.gamma, "effect")
    if method == "label_gradient":
        return influence.label_gradient_influence(t, w, v)
    if method == "random":
        return baselines.random_order(t)
    if method == "detector_a":
        return baselines.detector_a(t, state.rows, w, cfg)
    if method == "detector_b":
        return baselines.detector_b(t, state.val, w, v)
    return {"least_confidence": baselines.least_confidence, "entropy": baselines.entropy, "margin": baselines.margin}[method](t, w)


def choose(state: State, cfg: CleanConfig, b: int, method: str = "uplift", prune: bool = False) -> tuple[list, dict]:
    """The next rows (row_id, best_class) and what choosing them took."""
    began = time.perf_counter()
    state.v = v = influence_vector(state.rows, validation_gradient(state.val, state.w), state.w, cfg)
    n_pool = state.rows.size - len(state.edits)
    n = n_pool
    t0 = time.perf_counter()
    if method == "uplift" and prune and state.facts is not None and state.log:
        picks, n, t_grad = pruner.pruned_rows(state.facts, pruner.bracket_reach(v, state.w, state.w0, cfg.gamma, cfg.brackets), state.w, v, cfg.gamma, b, cfg.threshold, state.edits)
        if n > cfg.reanchor_at * n_pool:
            state.w0, state.v0 = state.w, v
            state.facts = written(pruner.facts(on_cluster(state), state.w, v), "provenance")
    else:
        scores = scores_by(state, method, v, cfg, b)
        picks = scores.top(b) if isinstance(scores, influence.LocalScores) else influence.select_top(scores, b).collect()
        t_grad = time.perf_counter() - t0
    now = time.perf_counter()
    return picks, {"n_candidates": n, "n_pool": n_pool, "t_inf": now - began, "t_grad": t_grad}


def picked_rows(state: State, wanted: list[int]) -> tuple[np.ndarray, np.ndarray, np.ndarray, np.ndarray]:
    """(row_id, x, weak, truth) of the picked rows, in order of id."""
    if isinstance(state.rows, LocalRows) and state.rows.truth is not None:
        at = np.flatnonzero(np.isin(state.rows.ids, wanted))
        return state.rows.ids[at], state.rows.x[at], state.rows.y[at], state.rows.truth[at]
    return as_arrays(state.train.where(F.col("row_id").isin(wanted)).orderBy("row_id"))


def edited_rows(state: State, ids: np.ndarray, new: np.ndarray, cfg: CleanConfig):
    """The training rows with these labels; arrays are changed in a copy, else the edited table is read."""
    if not isinstance(state.rows, LocalRows):
        return state.rows.edited(state.train, ids, new)
    at = np.searchsorted(state.rows.ids, ids)
    y, clean = state.rows.y.copy(), state.rows.clean.copy()
    y[at], clean[at] = new, True
    return replace(state.rows, y=y, clean=clean)


def clean(state: State, picks: list, cfg: CleanConfig, update: str = "replay", method: str = "uplift") -> dict:
    """Labels for the picked rows, the edited view, and the refreshed model."""
    # a ranker without suggestions leaves its rows to annotators
    strategy = cfg.strategy if method in ("uplift", "detector_b") else "HUMAN3"
    suggested = {r.row_id: r.best_class for r in picks}
    ids, x, old, truth = picked_rows(state, list(suggested))
    votes = None
    if state.votes is not None and strategy != "SUGGEST":
        votes = [(r.row_id, r.label) for r in state.votes.where(F.col("row_id").isin(list(suggested))).select("row_id", "label").collect()]
    # a truth of -1 is none
    known = {i: t for i, t in zip(ids.tolist(), truth.tolist()) if t >= 0}
    labels = annotate.clean_few(suggested, strategy, known, cfg.classes, cfg.annotator_error, votes)
    at = np.isin(ids, list(labels))
    ids, x, old, truth = ids[at], x[at], old[at], truth[at]
    new = np.eye(cfg.classes)[[labels[i] for i in ids]] if len(ids) else old
    t0 = time.perf_counter()
    before, explicit = state.rows, len(state.trace)
    state.edits, state.seen = state.edits | labels, None
    state.rows = edited_rows(state, ids, new, cfg)
    if update == "replay":
        state.w, state.trace, explicit = replay_label_edits(before, state.trace, ids, x, old, new, cfg)
    elif update == "warm":
        state.w, state.trace = warm_refit(state.rows, cfg, state.w, cfg.warm_steps)
        explicit = len(state.trace)
    else:
        state.w, state.trace = retrain(state.rows, cfg)
    took = time.perf_counter() - t0
    agreed = int(sum(suggested[i] == t for i, t in zip(ids.tolist(), truth.tolist())))
    return {"t_update": took, "agreed": agreed, "votes": annotate.annotation_cost(strategy, len(labels)), "explicit": explicit}


def measured(state: State) -> dict:
    val, test = quality(state.val, state.w), quality(state.test, state.w)
    return {"val_loss": val["loss"], "val_f1": val["f1"], "test_f1": test["f1"]}


def run_loop(
    train: DataFrame, cfg: CleanConfig, method: str = "uplift", update: str = "replay", prune: bool = False, stop: Callable[[dict], bool] | None = None,
    start: State | None = None, votes: DataFrame | None = None, each: Callable[[State, list], None] | None = None,
) -> State:
    """Rounds until the budget is spent, the pool is empty or ``stop`` says so; ``state.log`` has a row a round.

    ``start`` is a state to begin from instead of a first training (it isn't changed), first or resumed;
    its edits count against the budget;
    ``each`` sees the state before every round's labels, with the round's picks.
    """
    state = initialise(train, cfg, prune) if start is None else replace(start, edits=dict(start.edits), log=[])
    state.votes = votes
    state.log.append({"round": 0, "n_cleaned": len(state.edits), "n_candidates": 0, "n_pool": state.rows.size - len(state.edits), "agreed": 0, "votes": 0, "t_inf": 0.0, "t_grad": 0.0, "t_update": 0.0, **measured(state)})
    k = 0
    while len(state.edits) < cfg.budget:
        if stop is not None and stop(state.log[-1]):
            break
        picks, spent = choose(state, cfg, min(cfg.round_size, cfg.budget - len(state.edits)), method, prune and bool(state.edits))
        if not picks:
            break
        if each is not None:
            each(state, picks)
        k += 1
        n = len(state.edits)
        done = clean(state, picks, cfg, update, method)
        state.log.append({"round": k, "n_cleaned": len(state.edits), **spent, **{c: done[c] for c in ("agreed", "votes", "t_update")}, **measured(state)})
        if len(state.edits) == n:
            break
    return state
