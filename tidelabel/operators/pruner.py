"""Interval pruner: brackets of the current scores from facts kept since an earlier model.

At the anchor model W0 each row keeps p0 and the largest eigenvalue h of its Hessian. In
round k, with v of the current model and drift D = W_k - W0, every score is bracketed
around a centre that uses p0. Rows whose bracket can't reach the b best are settled;
only the others are scored with the current model.

Kinds of brackets: ``printed`` (class terms at full width), ``half`` (class terms at
half width, enough for positive semidefinite Hessians), ``softmax_exact`` (class terms
cancel under softmax, only the re-weighting term has width). ``mu`` = ``ceiling`` takes
h = |x|^2 / 2, an upper bound at any model, so that the bracket is guaranteed.

The prescreen goes further: with s0 = V0 x and |x| kept, |s - s0| <= |V - V0| |x| bounds
all scores without reading x at all, and only rows in reach are read.

The facts stand beside the features and weak labels in one table of blocks, so no round joins
anything: brackets are one pass over it, and the candidates are scored from its rows.
Rows cleaned since, at most the budget, are left out by a list of ids.
"""

from __future__ import annotations

import time
from collections.abc import Callable
from dataclasses import dataclass

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame, Observation, Row
from pyspark.sql import functions as F

from tidelabel.operators.core import ClusterRows, blocks, hessian_norms, packed, softmax
from tidelabel.operators.influence import pool, score_batch, scored, select_top, smallest, uplift_scores
from tidelabel.schema import SCORES

PROVENANCE = "row_id bigint, x array<double>, weak array<double>, p0 array<double>, h double, x_norm double, s0 array<double>"
FACTS = ("row_id", "x", "weak", "p0", "h", "x_norm", "s0")
BOUNDS = "row_id bigint, center array<double>, lower array<double>, upper array<double>, x array<double>, weak array<double>"


def _lists(a: np.ndarray) -> pa.Array:
    return pa.ListArray.from_arrays(pa.array(np.arange(len(a) + 1, dtype=np.int32) * a.shape[1]), pa.array(np.ascontiguousarray(a).ravel()))


def provenance(train: DataFrame, w0: np.ndarray, v0: np.ndarray) -> DataFrame:
    """Features and weak labels of the pool with the C + C + 2 numbers that later rounds need of each row."""
    return unpacked(facts(train, w0, v0))


def facts(train: DataFrame | ClusterRows, w0: np.ndarray, v0: np.ndarray) -> DataFrame:
    """The same by blocks, see ``packed``."""

    def of(ids, x, y):
        p = softmax(x @ w0.T)
        values = (ids, x, y, p, hessian_norms(x, p), np.sqrt((x**2).sum(axis=1)), x @ v0.T)
        return pa.RecordBatch.from_arrays([pa.array([np.ascontiguousarray(v).tobytes()], pa.binary()) for v in values], names=list(FACTS))

    def run(batches):
        for found in blocks(batches, ("x", "weak")):
            yield of(*found)

    rows, schema = pool(train), ", ".join(f"{n} binary" for n in FACTS)
    return rows.over(lambda part: of(part.ids, part.x, part.y), schema) if isinstance(rows, ClusterRows) else packed(rows.select("row_id", "x", "weak")).mapInArrow(run, schema)


def unpacked(found: DataFrame) -> DataFrame:
    """PROVENANCE rows of ``facts``."""

    def run(batches):
        for values in blocks(batches, FACTS[1:]):
            yield pa.RecordBatch.from_arrays([_lists(v) if v.ndim == 2 else pa.array(v) for v in values], names=list(FACTS))

    return found.mapInArrow(run, PROVENANCE)


def left(prov: DataFrame, done=()) -> DataFrame:
    """The rows not cleaned since; ``done`` are at most the budget."""
    return prov.where(~F.col("row_id").isin(list(done))) if done else prov


@dataclass(frozen=True)
class Drift:
    along: float  # v . (W_k - W0)
    size: float  # |v| |W_k - W0|


def drift(v: np.ndarray, w: np.ndarray, w0: np.ndarray) -> Drift:
    d = w - w0
    return Drift(float((v * d).sum()), float(np.sqrt((v**2).sum() * (d**2).sum())))


def bracket(s, y, p0, h, gamma: float, d: Drift, kind: str) -> tuple[np.ndarray, np.ndarray, np.ndarray]:
    """(centre, lower, upper) [n, classes] from s = V x, weak labels, p0 and Hessian norms."""
    if kind not in ("printed", "half", "softmax_exact"):
        raise ValueError(kind)
    ys = (y * s).sum(axis=1, keepdims=True)
    centre = ys - s + (1 - gamma) * ((p0 * s).sum(axis=1, keepdims=True) - ys)
    shift = (1 - gamma) / 2 * d.along * h[:, None]
    radius = (1 - gamma) / 2 * d.size * h[:, None]
    if kind != "softmax_exact":
        # sum of |delta_j| over classes for delta = one-hot - y; the sum of delta itself is nought
        moved = np.abs(y).sum(axis=1, keepdims=True) - np.abs(y) + np.abs(1 - y)
        radius = radius + (1.0 if kind == "printed" else 0.5) * d.size * moved * h[:, None]
    return centre, centre + shift - radius, centre + shift + radius


def brackets(prov: DataFrame, v, w, w0, gamma: float, kind: str = "softmax_exact", mu: str = "anchor", done=()) -> DataFrame:
    """BOUNDS of the rows left, in one pass."""
    d = drift(v, w, w0)

    def run(batches):
        for b in batches:
            if b.num_rows:
                x, y, p0 = (b.column(i).flatten().to_numpy().reshape(b.num_rows, -1) for i in (1, 2, 3))
                h = b.column(4).to_numpy() if mu == "anchor" else (x**2).sum(axis=1) / 2
                yield pa.RecordBatch.from_arrays([b.column(0), *map(_lists, bracket(x @ v.T, y, p0, h, gamma, d, kind)), b.column(1), b.column(2)], names=["row_id", "center", "lower", "upper", "x", "weak"])

    return left(prov, done).select("row_id", "x", "weak", "p0", "h").mapInArrow(run, BOUNDS)


def prescreen(prov: DataFrame, v, v0, w, w0, gamma: float, done=()) -> DataFrame:
    """BOUNDS without reading x, in column expressions: s lies within |V_c - V0_c| |x| of s0.

    |delta.(s - s0)| and the re-weighting term's share are bounded entry by entry, the
    change of p by the Hessian bracket at its ceiling.
    """
    reach, d, n = np.sqrt(((v - v0) ** 2).sum(axis=1)), drift(v, w, w0), len(v)
    at = lambda name: [F.col(name)[c] for c in range(n)]
    y, p0, s0, size = at("weak"), at("p0"), at("s0"), F.col("x_norm")
    # entries of the score's coefficients: y - e_c + (1 - gamma) (p0 - y)
    base = [yc + (1 - gamma) * (pc - yc) for yc, pc in zip(y, p0)]
    whole = sum((bc * sc for bc, sc in zip(base, s0)), F.lit(0.0))
    wide = sum((F.abs(bc) * float(r) for bc, r in zip(base, reach)), F.lit(0.0))
    h = size * size / 2
    rows = left(prov, done).select("row_id", "x", "weak", "s0", "x_norm", *(b.alias(f"b{c}") for c, b in enumerate(base)), whole.alias("whole"), wide.alias("wide"), h.alias("h"))
    centre = [F.col("whole") - sc for sc in s0]
    slack = [(F.col("wide") - F.abs(F.col(f"b{c}")) * float(reach[c]) + F.abs(F.col(f"b{c}") - 1) * float(reach[c])) * size for c in range(n)]
    shift, radius = (1 - gamma) / 2 * d.along * F.col("h"), (1 - gamma) / 2 * d.size * F.col("h")
    low = [c + shift - radius - k for c, k in zip(centre, slack)]
    high = [c + shift + radius + k for c, k in zip(centre, slack)]
    return rows.select("row_id", *(F.array(*v).alias(name) for name, v in (("center", centre), ("lower", low), ("upper", high))), "x", "weak")


def per_row(bounds: DataFrame) -> DataFrame:
    """(row_id, center, upper, least_upper, lower): a row's best class and the ends that decide."""
    best = F.array_position("center", F.array_min("center")).cast("int")
    return bounds.select("row_id", F.array_min("center").alias("center"), F.element_at("upper", best).alias("upper"), F.array_min("upper").alias("least_upper"), F.array_min("lower").alias("lower"))


def limit_of(rows: DataFrame, b: int, threshold: str = "printed") -> DataFrame:
    """(limit): rows of ``per_row`` whose lower end is above it are settled.

    ``printed``: the limit is the largest upper end among the b rows of best centre;
    ``tight``: the b-th smallest upper end over all rows.
    """
    order, end = ("center", "upper") if threshold == "printed" else ("least_upper", "least_upper")
    return rows.orderBy(order, "row_id").limit(b).agg(F.max(end).alias("limit"))


def candidates(bounds: DataFrame, b: int, threshold: str = "printed") -> DataFrame:
    """(row_id): rows that may be among the b best. Rows count once; a lower end equal to the limit stays in."""
    rows = per_row(bounds)
    return rows.join(F.broadcast(limit_of(rows, b, threshold)), rows.lower <= F.col("limit"), "left_semi").select("row_id")


def pruned_top(bounds: DataFrame, w, v, gamma: float, b: int, threshold: str = "printed") -> tuple[DataFrame, int, float]:
    """(the b best with exact scores of the candidates only, candidates, seconds that scoring took).

    Two passes: one finds the limit, the other scores the rows whose lower end reaches it.
    """
    limit = limit_of(per_row(bounds), b, threshold).first().limit
    began, seen = time.perf_counter(), Observation()
    kept = bounds.where(F.array_min("lower") <= F.lit(limit)).select("row_id", "x", "weak").observe(seen, F.count(F.lit(1)).alias("n"))
    best = select_top(scored(kept, lambda x, y: uplift_scores(x, y, w, v, gamma)), b)
    picks = bounds.sparkSession.createDataFrame(best.collect(), best.schema)
    return picks, seen.get["n"], time.perf_counter() - began


@dataclass(frozen=True)
class Reach:
    """Brackets as a function of arrays: the facts of PROVENANCE that it reads, and (centre, lower, upper) [n, classes] from them."""

    facts: tuple[str, ...]
    of: Callable[..., tuple[np.ndarray, np.ndarray, np.ndarray]]


def bracket_reach(v, w, w0, gamma: float, kind: str = "softmax_exact", mu: str = "anchor") -> Reach:
    """``brackets`` as a function."""
    d = drift(v, w, w0)
    return Reach(("x", "weak", "p0", "h"), lambda x, y, p0, h: bracket(x @ v.T, y, p0, h if mu == "anchor" else (x**2).sum(axis=1) / 2, gamma, d, kind))


def prescreen_reach(v, v0, w, w0, gamma: float) -> Reach:
    """``prescreen`` as a function; x isn't among its facts."""
    reach, d = np.sqrt(((v - v0) ** 2).sum(axis=1)), drift(v, w, w0)

    def of(y, p0, s0, size):
        base = y + (1 - gamma) * (p0 - y)
        sizes, h = np.abs(base), size * size / 2
        centre = (base * s0).sum(axis=1, keepdims=True) - s0
        slack = ((sizes * reach).sum(axis=1, keepdims=True) - sizes * reach + np.abs(base - 1) * reach) * size[:, None]
        shift, radius = ((1 - gamma) / 2 * m * h[:, None] for m in (d.along, d.size))
        return centre, centre + shift - radius - slack, centre + shift + radius + slack

    return Reach(("weak", "p0", "s0", "x_norm"), of)


def pruned_rows(found: DataFrame, reach: Reach, w, v, gamma: float, b: int, threshold: str = "printed", done=()) -> tuple[list[Row], int, float]:
    """What ``pruned_top`` gives of the reach's brackets on ``facts``, its rows collected.

    Brackets are made, compared and dropped within a task: of a block come the b rows that
    decide the limit, then the b best candidates and how many there are.
    """
    names, gone = list(reach.facts), np.array(sorted(done), np.int64)

    def ends(batches):
        for ids, *values in blocks(batches, names):
            centre, _, upper = reach.of(*values)
            if threshold == "printed":
                best = centre.argmin(axis=1)
                order, end = (m[np.arange(len(best)), best] for m in (centre, upper))
            else:
                order = end = upper.min(axis=1)
            left_in = ~np.isin(ids, gone)
            ids, order, end = ids[left_in], order[left_in], end[left_in]
            at = smallest(order, ids, b)
            yield pa.RecordBatch.from_arrays([pa.array(ids[at]), pa.array(order[at]), pa.array(end[at])], names=["row_id", "place", "end"])

    limit = found.select("row_id", *names).mapInArrow(ends, "row_id long, place double, end double").orderBy("place", "row_id").limit(b).agg(F.max("end").alias("limit")).first().limit
    if limit is None:
        return [], 0, 0.0
    began, more = time.perf_counter(), [n for n in ("x", "weak") if n not in names]

    def exact(batches):
        for ids, *values in blocks(batches, [*names, *more]):
            of = dict(zip([*names, *more], values))
            low = reach.of(*(of[n] for n in names))[1].min(axis=1)
            # as in Spark, NaN is above every number
            kept = np.flatnonzero(((low <= limit) | np.isnan(limit)) & ~np.isin(ids, gone))
            if len(kept):
                best = score_batch(ids[kept], uplift_scores(of["x"][kept], of["weak"][kept], w, v, gamma), b)
                yield best.append_column("n", pa.array([len(kept)] + [0] * (best.num_rows - 1), pa.int64()))

    got = found.select("row_id", *names, *more).mapInArrow(exact, f"{SCORES}, n long").collect()
    best = sorted(got, key=lambda r: (np.isnan(r.best_score), r.best_score, r.row_id))[:b]
    return best, sum(r.n for r in got), time.perf_counter() - began


def violations(bounds: DataFrame, exact: DataFrame, slack: float = 1e-9) -> int:
    """(row, class) pairs whose exact score lies outside its bracket."""
    both = bounds.join(exact.select("row_id", "scores"), "row_id")
    inside = F.expr(f"size(filter(sequence(0, size(scores) - 1), i -> scores[i] < lower[i] - {slack} or scores[i] > upper[i] + {slack}))")
    return both.agg(F.coalesce(F.sum(inside), F.lit(0)).alias("n")).first().n


def cost(n_rows: int, classes: int, model_size: int, n_candidates: int) -> dict[str, int]:
    """Multiplications: brackets of all pairs, and gradients of the candidates, against all gradients."""
    return {"brackets": n_rows * classes * (classes * model_size + model_size + classes), "candidates": n_candidates * classes * model_size, "full": n_rows * classes * model_size}
