"""The weighted softmax objective: loss, gradient, Hessian products, solvers and trainers.

The objective is (1/N) * sum of weight * cross-entropy, plus lam/2 |W|^2 added once. A
training set is read through ``Rows``: of a size that the driver may hold it is kept
as arrays there, otherwise each sum is one pass over the cluster, made of partial
sums by task that Spark adds up. What comes to the driver has the model's size.
"""

from __future__ import annotations

from collections.abc import Callable, Iterator
from concurrent.futures import ThreadPoolExecutor
from copy import copy
from dataclasses import dataclass, field

import numpy as np
import pyarrow as pa
from pyspark import inheritable_thread_target
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from tidelabel.config import CleanConfig
from tidelabel.sources.sinks import written
from tidelabel.sources.tables import as_arrays

#: Bytes of mini-batches that the driver fetches at once, fetches under way beside it, and epochs whose order it remembers.
FETCH_BYTES = 32 << 20
AHEAD = 2
EPOCHS = 4
#: Rows of a block at most, and rows that a task deals out at once; columns of blocks that aren't double, and those of lists.
BLOCK = 1 << 13
DEALT = 1 << 18
KINDS = {"row_id": np.int64, "is_clean": np.bool_}
LISTS = ("x", "weak", "p0", "s0")


def softmax(z: np.ndarray) -> np.ndarray:
    e = np.exp(z - z.max(axis=-1, keepdims=True))
    return e / e.sum(axis=-1, keepdims=True)


def loss_of(x, y, weight, w) -> np.ndarray:
    z = x @ w.T
    top = z.max(axis=1, keepdims=True)
    log_p = z - top - np.log(np.exp(z - top).sum(axis=1, keepdims=True))
    return -(y * log_p).sum(axis=1) * weight


def gradient_of(x, y, weight, w) -> np.ndarray:
    """Sum over rows of weight * (p - y) x'."""
    return ((softmax(x @ w.T) - y) * weight[:, None]).T @ x


def hessian_product_of(x, weight, w, u) -> np.ndarray:
    """Sum over rows of weight * A_p (u x) x' with A_p = diag(p) - pp'."""
    p, s = softmax(x @ w.T), x @ u.T
    return ((p * (s - (p * s).sum(axis=1, keepdims=True))) * weight[:, None]).T @ x


def hessian_of(x, weight, w) -> np.ndarray:
    p = softmax(x @ w.T)
    c, d = p.shape[1], x.shape[1]
    h = np.empty((c, d, c, d))
    for i in range(c):
        for j in range(c):
            a = weight * p[:, i] * ((i == j) - p[:, j])
            h[i, :, j, :] = (x * a[:, None]).T @ x
    return h.reshape(c * d, c * d)


def hessian_norms(x: np.ndarray, p: np.ndarray, steps: int = 60) -> np.ndarray:
    """Largest eigenvalue of each row's Hessian: |x|^2 times A_p's, by power iteration on C x C matrices."""
    if p.shape[1] == 2:
        return 2 * p[:, 0] * p[:, 1] * (x**2).sum(axis=1)
    v = p * 0 + 1.0 + np.arange(p.shape[1]) * 0.1
    v = v + (p == p.max(axis=1, keepdims=True)) * 1.0
    value = np.zeros(len(p))
    for _ in range(steps):
        av = p * (v - (p * v).sum(axis=1, keepdims=True))
        norm = np.sqrt((av**2).sum(axis=1))
        value = norm / np.maximum(np.sqrt((v**2).sum(axis=1)), 1e-300)
        v = av / np.maximum(norm, 1e-300)[:, None]
    return value * (x**2).sum(axis=1)


def batch_of(row_id, epoch: int, batches: int):
    """A row's mini-batch in an epoch: arithmetic on the id, so that no membership is stored. Arrays or columns."""
    mixed = (row_id * 7919 + epoch * 104729) % 1000003
    return mixed % batches


def packed(rows: DataFrame) -> DataFrame:
    """``rows`` by blocks: a row holds BLOCK rows at most, each column as the bytes of its values.

    A pass over features as lists is mostly spent on handing them over list by list.
    """
    names = rows.columns

    def run(batches):
        for found in batches:
            for at in range(0, found.num_rows, BLOCK):
                b = found.slice(at, BLOCK)
                values = (c.flatten() if pa.types.is_list(c.type) else c for c in b.columns)
                yield pa.RecordBatch.from_arrays([pa.array([np.ascontiguousarray(v.to_numpy(zero_copy_only=False)).tobytes()], pa.binary()) for v in values], names=names)

    return rows.mapInArrow(run, ", ".join(f"{n} binary" for n in names))


def _cuts(values: np.ndarray, ends: np.ndarray) -> pa.Array:
    """Rows of ``values`` between one end and the next, each as a binary value."""
    flat = np.ascontiguousarray(values)
    offsets = (ends * (flat.nbytes // max(len(flat), 1))).astype(np.int32)
    return pa.Array.from_buffers(pa.binary(), len(ends) - 1, [None, pa.py_buffer(offsets), pa.py_buffer(flat)])


def blocks(batches, names) -> Iterator[list[np.ndarray]]:
    """The named columns of every block of ``packed``; row_id is among those read."""
    for found in batches:
        columns = [found.column(n) for n in ("row_id", *names)]
        for i in range(found.num_rows):
            ids, *values = (np.frombuffer(c[i].as_buffer(), KINDS.get(n, np.float64)) for n, c in zip(("row_id", *names), columns))
            yield [ids, *(v.reshape(len(ids), -1) if n in LISTS else v for n, v in zip(names, values))]


@dataclass
class LocalRows:
    """A training set as arrays on the driver."""

    ids: np.ndarray
    x: np.ndarray
    y: np.ndarray
    clean: np.ndarray
    gamma: float
    truth: np.ndarray | None = None
    order: dict = field(default_factory=dict, repr=False, compare=False)  # of ids alone: copies with other labels share it

    @property
    def size(self) -> int:
        return len(self.ids)

    @property
    def shape(self) -> tuple[int, int]:
        return self.y.shape[1], self.x.shape[1]

    def total(self, fn: Callable, batch: tuple[int, int, int] | None = None) -> tuple[np.ndarray, int]:
        """(sum of fn(x, y, weight), rows) over all rows or one (epoch, number, batches)."""
        if batch is None or batch[2] == 1:
            return fn(self.x, self.y, np.where(self.clean, 1.0, self.gamma)), self.size
        at = self.members(*batch)
        return fn(self.x[at], self.y[at], np.where(self.clean[at], 1.0, self.gamma)), len(at)

    def members(self, epoch: int, number: int, batches: int) -> np.ndarray:
        """Places of a mini-batch's rows, rising; an epoch is dealt out once."""
        if (epoch, batches) not in self.order:
            of = batch_of(self.ids, epoch, batches)
            for old in list(self.order)[: max(0, len(self.order) - EPOCHS + 1)]:
                self.order.pop(old, None)
            self.order[epoch, batches] = np.argsort(of, kind="stable"), np.concatenate([[0], np.cumsum(np.bincount(of, minlength=batches))])
        at, ends = self.order[epoch, batches]
        return at[ends[number] : ends[number + 1]]

    def each_batch(self, keys: list[tuple[int, int, int]]) -> Iterator[Batch]:
        return (Batch(self, k) for k in keys)


def edited_labels(ids: np.ndarray, y: np.ndarray, clean: np.ndarray, edits: dict[int, np.ndarray]) -> tuple[np.ndarray, np.ndarray]:
    """(labels, marks) with the edits among these rows put in, in copies."""
    at = np.flatnonzero(np.isin(ids, np.fromiter(edits, np.int64, len(edits)))) if edits else ()
    if len(at):
        y, clean = y.copy(), clean.copy()
        y[at], clean[at] = [edits[i] for i in ids[at].tolist()], True
    return y, clean


@dataclass
class Batch:
    """One (epoch, number, batches) of a training set, summed by it."""

    rows: LocalRows | ClusterRows
    key: tuple[int, int, int]

    def total(self, fn: Callable, batch=None) -> tuple[np.ndarray, int]:
        return self.rows.total(fn, self.key)


class ClusterRows:
    """A training set as a DataFrame; every sum over all rows is one distributed pass, over blocks that are written once.

    A path over mini-batches makes a step at a time, so that a job a step would take
    mostly the jobs' fixed costs. Instead the rows are written once an epoch, dealt out to
    its mini-batches, and the driver fetches these in the order of the steps, FETCH_BYTES
    at once. Edits since, at most the budget, are put in there. Mini-batches too large
    for that stay distributed passes.
    """

    def __init__(self, train: DataFrame, gamma: float):
        self.train, self.gamma = train.select("row_id", "x", "weak", "is_clean"), gamma
        first = self.train.select(F.size("weak").alias("c"), F.size("x").alias("d")).first()
        self.shape = (first.c, first.d) if first else (0, 0)
        self.size = self.train.count()
        self.base, self.dealt, self.edits, self.pooled = self.train, {}, {}, False

    def edited(self, train: DataFrame, ids: np.ndarray, new: np.ndarray) -> ClusterRows:
        """These rows with new labels for ``ids``, as ``train`` has them; what is dealt out is kept."""
        out = object.__new__(ClusterRows)
        out.train, out.gamma, out.shape, out.size = train.where("split = 'train'").select("row_id", "x", "weak", "is_clean"), self.gamma, self.shape, self.size
        out.base, out.dealt, out.edits, out.pooled = self.base, self.dealt, self.edits | dict(zip(ids.tolist(), new)), self.pooled
        return out

    def uncleaned(self) -> ClusterRows:
        """A view of the rows not cleaned yet, for ``over``."""
        out = copy(self)
        out.pooled = True
        return out

    def over(self, fn: Callable[[LocalRows], pa.RecordBatch | None], schema: str) -> DataFrame:
        """What ``fn`` gives of every block, in one pass."""
        edits, gamma, pooled = self.edits, self.gamma, self.pooled

        def run(batches):
            for ids, x, y, clean in blocks(batches, ("x", "weak", "is_clean")):
                part = LocalRows(ids, x, *edited_labels(ids, y, clean, edits), gamma)
                if pooled and part.clean.any():
                    m = ~part.clean
                    part = LocalRows(ids[m], x[m], part.y[m], part.clean[m], gamma)
                out = fn(part) if part.size else None
                if out is not None:
                    yield out

        return self.stored().mapInArrow(run, schema)

    def stored(self) -> DataFrame:
        """The unedited rows by blocks; as ``dealt`` is shared by all edited copies, so are they."""
        if "blocks" not in self.dealt:
            self.dealt["blocks"] = written(packed(self.base), "rows")
        return self.dealt["blocks"]

    def at_once(self, batches: int) -> int:
        """Mini-batches that the driver fetches at once; 0 where they are too large."""
        each = (sum(self.shape) + 2) * 8 * -(-self.size // batches)
        return 0 if batches == 1 or 8 * each > FETCH_BYTES else FETCH_BYTES // max(each, 1)

    def deal(self, epoch: int, batches: int) -> DataFrame:
        """(run, number, ids, x, y, clean): the epoch's mini-batches as bytes, ``run`` counts what is fetched at once."""
        if (epoch, batches) not in self.dealt:
            run_of = self.at_once(batches)

            def cut(held):
                """Rows of some blocks by mini-batch: a binary value for each, cut from the bytes of all."""
                ids = np.concatenate([h[0] for h in held])
                of = batch_of(ids, epoch, batches)
                order = np.argsort(of, kind="stable")
                starts = np.flatnonzero(np.diff(of[order], prepend=-1))
                ends, values = np.append(starts, len(order)), (ids, *(np.concatenate([h[i] for h in held]) for i in (1, 2, 3)))
                return pa.RecordBatch.from_arrays([pa.array(of[order][starts].astype(np.int32)), *(_cuts(v[order], ends) for v in values)], names=["number", "ids", "x", "y", "clean"])

            def deal(found):
                held, n = [], 0
                for values in blocks(found, ("x", "weak", "is_clean")):
                    held, n = [*held, values], n + len(values[0])
                    if n >= DEALT:
                        yield cut(held)
                        held, n = [], 0
                if held:
                    yield cut(held)

            def join(found):
                for b in found:
                    number = b.column(0).to_numpy()
                    starts = np.flatnonzero(np.diff(number, prepend=-1))
                    ends = np.append(starts, len(number))
                    # one mini-batch's values stand side by side
                    for at in range(0, len(starts), run_of):
                        some = ends[at : at + run_of + 1]
                        n = number[some[:-1]]
                        yield pa.RecordBatch.from_arrays([pa.array(n // run_of), pa.array(n), *(pa.array([b"".join(c[i:j].to_pylist()) for i, j in zip(some, some[1:])], pa.binary()) for c in b.columns[1:])], names=["run", "number", "ids", "x", "y", "clean"])

            parts = "number int, ids binary, x binary, y binary, clean binary"
            dealt = self.stored().mapInArrow(deal, parts).repartition("number").sortWithinPartitions("number")
            self.dealt[epoch, batches] = written(dealt.mapInArrow(join, f"run int, {parts}"), "batches", "run")
        return self.dealt[epoch, batches]

    def each_batch(self, keys: list[tuple[int, int, int]]) -> Iterator[Batch | LocalRows]:
        """The mini-batches one after another, in the order of ``keys``."""
        parts, at = [], 0
        while at < len(keys):
            epoch, _, batches = keys[at]
            most = self.at_once(batches)
            part = keys[at : at + max(most, 1)]
            parts.append((most, part[: next((i for i, k in enumerate(part) if (k[0], k[2]) != (epoch, batches)), len(part))]))
            at += len(parts[-1][1])
        with ThreadPoolExecutor(AHEAD) as ahead:
            # while the steps of one part are made, the next ones are on their way
            fetch = inheritable_thread_target(self.train.sparkSession)(self.fetched)
            ask = lambda i: ahead.submit(fetch, parts[i][1]) if i < len(parts) and parts[i][0] else None
            for epoch, batches in dict.fromkeys((p[0][0], p[0][2]) for most, p in parts if most):
                self.deal(epoch, batches)
            coming = [ask(i) for i in range(AHEAD)]
            for i, (most, part) in enumerate(parts):
                now = coming.pop(0)
                pieces = now.result() if now else None
                coming.append(ask(i + AHEAD))
                for k in part:
                    yield self.local(pieces.pop(k[1], [])) if most else Batch(self, k)

    def fetched(self, part: list[tuple[int, int, int]]) -> dict[int, list[dict]]:
        """The pieces of mini-batches of one epoch, by number."""
        epoch, _, batches = part[0]
        most, numbers = self.at_once(batches), [k[1] for k in part]
        found = self.deal(epoch, batches).where(F.col("run").isin(sorted({n // most for n in numbers})) & F.col("number").isin(numbers)).drop("run").toArrow().to_pylist()
        pieces: dict[int, list] = {}
        for r in found:
            pieces.setdefault(r["number"], []).append(r)
        return pieces

    def local(self, pieces: list[dict]) -> LocalRows:
        """The rows of one mini-batch, with the edits since."""
        c, d = self.shape
        whole = lambda name, kind: np.concatenate([np.empty(0, kind), *(np.frombuffer(p[name], kind) for p in pieces)])
        ids, x, y, clean = whole("ids", np.int64), whole("x", np.float64).reshape(-1, d), whole("y", np.float64).reshape(-1, c), whole("clean", np.bool_)
        order = np.argsort(ids, kind="stable")
        ids, x, y, clean = ids[order], x[order], y[order], clean[order]
        return LocalRows(ids, x, *edited_labels(ids, y, clean, self.edits), self.gamma)

    def total(self, fn: Callable, batch: tuple[int, int, int] | None = None) -> tuple[np.ndarray, int]:
        def run(part):
            if batch is not None:
                m = batch_of(part.ids, batch[0], batch[2]) == batch[1]
                part = LocalRows(part.ids[m], part.x[m], part.y[m], part.clean[m], part.gamma)
            if part.size:
                flat = np.append(np.ravel(fn(part.x, part.y, np.where(part.clean, 1.0, part.gamma))), part.size)
                return pa.RecordBatch.from_arrays([pa.array(np.arange(len(flat), dtype=np.int32)), pa.array(flat.astype(float))], names=["i", "v"])

        parts = self.over(run, "i int, v double").groupBy("i").agg(F.sum("v").alias("v")).orderBy("i").toArrow()
        flat = parts["v"].to_numpy()
        if not len(flat):
            return np.zeros(1), 0
        return flat[:-1], int(flat[-1])


def rows_of(train: DataFrame, cfg: CleanConfig) -> LocalRows | ClusterRows:
    """The training part of ``train``, held locally while its size allows."""
    part = train.where("split = 'train'")
    n = part.select(F.count("*").alias("n"), F.max(F.size("x")).alias("d")).first()
    if n.n and n.n * (n.d + cfg.classes + 2) * 8 <= cfg.local_bytes:
        ids, x, y, truth, clean = as_arrays(part.orderBy("row_id"), "is_clean")
        return LocalRows(ids, x, y, clean, cfg.gamma, truth)
    return ClusterRows(part, cfg.gamma)


def objective(rows, w: np.ndarray, lam: float) -> float:
    s, _ = rows.total(lambda x, y, g: np.array([loss_of(x, y, g, w).sum()]))
    return float(np.ravel(s)[0] / rows.size + lam / 2 * (w**2).sum())


def gradient(rows, w: np.ndarray, lam: float, batch=None) -> tuple[np.ndarray, int]:
    """(gradient of the objective, rows) on all rows or one mini-batch; an empty batch has the penalty's."""
    s, n = rows.total(lambda x, y, g: gradient_of(x, y, g, w), batch)
    data = np.reshape(s, w.shape) / n if n else 0.0
    return data + lam * w, n


def hvp(rows, w: np.ndarray, u: np.ndarray, lam: float) -> np.ndarray:
    s, n = rows.total(lambda x, y, g: hessian_product_of(x, g, w, u))
    return np.reshape(s, w.shape) / n + lam * u


def hessian(rows, w: np.ndarray, lam: float) -> np.ndarray:
    s, n = rows.total(lambda x, y, g: hessian_of(x, g, w))
    return np.reshape(s, (w.size, w.size)) / n + lam * np.eye(w.size)


def train_gd(rows, cfg: CleanConfig, steps: int, start: np.ndarray | None = None) -> np.ndarray:
    w = np.zeros(rows.shape) if start is None else start.copy()
    for _ in range(steps):
        w = w - cfg.rate * gradient(rows, w, cfg.lam)[0]
    return w


def train_newton(rows, cfg: CleanConfig, start: np.ndarray | None = None, most: int = 30) -> np.ndarray:
    """The optimum by Newton steps with a dense Hessian; for models of up to a few thousand entries."""
    w = np.zeros(rows.shape) if start is None else start.copy()
    for _ in range(most):
        step = np.linalg.solve(hessian(rows, w, cfg.lam), gradient(rows, w, cfg.lam)[0].ravel()).reshape(w.shape)
        w = w - step
        if np.abs(step).max() < 1e-9:
            break
    return w


@dataclass
class Step:
    """One optimiser step: the parameters before it, its gradient, its batch's size."""

    w: np.ndarray
    g: np.ndarray
    n: int


def train_sgd(
    rows, cfg: CleanConfig, steps: int | None = None, stop: Callable[[np.ndarray], float] | None = None, patience: int = 3, start: np.ndarray | None = None
) -> tuple[np.ndarray, list[Step]]:
    """Mini-batch descent from ``start`` (zero) with its trace; ends early when ``stop`` (a validation loss) rises ``patience`` epochs running."""
    w, trace, best, bad = np.zeros(rows.shape) if start is None else start.copy(), [], np.inf, 0
    keys = [(*divmod(t, cfg.batches), cfg.batches) for t in range(cfg.steps if steps is None else steps)]
    for (_, number, _), part in zip(keys, rows.each_batch(keys)):
        g, n = gradient(part, w, cfg.lam)
        trace.append(Step(w, g, n))
        w = w - cfg.rate * g
        if stop is not None and number == cfg.batches - 1:
            now = stop(w)
            bad = bad + 1 if now > best else 0
            best = min(best, now)
            if bad >= patience:
                break
    return w, trace


def trusted_local(x: np.ndarray, truth: np.ndarray, classes: int, ids: np.ndarray | None = None) -> LocalRows:
    """Trusted rows held by the driver: their labels are the truth, their weight is 1."""
    return LocalRows(np.arange(len(x)) if ids is None else ids, x, np.eye(classes)[truth], np.ones(len(x), bool), 1.0, truth)


def trusted_rows(train: DataFrame, split: str, cfg: CleanConfig) -> LocalRows | ClusterRows:
    """A trusted split, held by the driver while its size allows; above that its sums are distributed passes."""
    part = train.where(F.col("split") == split).where("truth is not null")
    n = part.select(F.count("*").alias("n"), F.max(F.size("x")).alias("d")).first()
    if n.n * ((n.d or 0) + cfg.classes + 2) * 8 <= cfg.local_bytes:
        ids, x, _, truth = as_arrays(part.orderBy("row_id"))
        return trusted_local(x, truth, cfg.classes, ids)
    one_hot = F.transform(F.sequence(F.lit(0), F.lit(cfg.classes - 1)), lambda c: (c == F.col("truth")).cast("double"))
    return ClusterRows(part.select("row_id", "x", one_hot.alias("weak"), F.lit(True).alias("is_clean")), 1.0)


def validation_gradient(rows, w: np.ndarray) -> np.ndarray:
    """Mean gradient of the loss over trusted rows."""
    return gradient(rows, w, 0.0)[0] if rows.size else np.zeros_like(w)


def conjugate_gradient(product: Callable[[np.ndarray], np.ndarray], b: np.ndarray, start: np.ndarray | None = None, most: int = 200, tol: float = 1e-10) -> np.ndarray:
    v = np.zeros_like(b) if start is None else start.copy()
    r = b - product(v) if start is not None else b.copy()
    p, rr = r.copy(), float((r * r).sum())
    limit = tol**2 * max(float((b * b).sum()), 1e-300)
    for _ in range(most):
        if rr <= limit:
            break
        ap = product(p)
        a = rr / float((p * ap).sum())
        v, r = v + a * p, r - a * ap
        new = float((r * r).sum())
        p, rr = r + new / rr * p, new
    return v


def influence_vector(rows, val_gradient: np.ndarray, w: np.ndarray, cfg: CleanConfig, method: str = "auto", fraction: float = 1.0, start: np.ndarray | None = None) -> np.ndarray:
    """v = -H^-1 (validation gradient).

    ``cg``: one pass a turn; ``dense``: one pass in all, for small models; ``sampled``:
    conjugate gradients on the rows whose id's hash lies below ``fraction``.
    """
    if method == "auto":
        method = "dense" if w.size <= 1024 else "cg"
    if method == "dense":
        return -np.linalg.solve(hessian(rows, w, cfg.lam), val_gradient.ravel()).reshape(w.shape)
    if method == "sampled":
        rows = sampled(rows, fraction)
    return -conjugate_gradient(lambda u: hvp(rows, w, u, cfg.lam), val_gradient, None if start is None else -start)


def sampled(rows, fraction: float):
    """Rows whose hashed id falls into the first ``fraction`` of a thousand buckets."""
    buckets = max(1, round(1000 * fraction))
    if isinstance(rows, LocalRows):
        m = batch_of(rows.ids, 0, 1000) < buckets
        return LocalRows(rows.ids[m], rows.x[m], rows.y[m], rows.clean[m], rows.gamma)
    part = rows.train.where(F.pmod(F.pmod(F.col("row_id") * 7919, F.lit(1000003)), F.lit(1000)) < buckets)
    return ClusterRows(part, rows.gamma)


def difference_hvp(rows, w, u, lam: float, eps: float = 1e-6) -> np.ndarray:
    """A Hessian product by differences of gradients, for checks."""
    return (gradient(rows, w + eps * u, lam)[0] - gradient(rows, w - eps * u, lam)[0]) / (2 * eps)
