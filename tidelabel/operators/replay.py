"""Model refresh by replaying the cached optimiser path, and full retraining.

A step's batch gradient on edited data is that of the unedited data at the new
parameters, less the removed rows' part, plus the added rows' part. The first is
computed in the first ``burn_in`` steps and in every ``period``-th, and otherwise
estimated: cached gradient + B (w' - w), with B from the last curvature pairs.
"""

from __future__ import annotations

from dataclasses import dataclass

import numpy as np

from tidelabel.config import CleanConfig
from tidelabel.operators.core import Step, batch_of, gradient, gradient_of, train_sgd


class CurvatureMemory:
    """The last pairs (step, change of gradient) and products with their quasi-Newton matrix."""

    def __init__(self, size: int):
        self.size, self.s, self.y = size, [], []

    def add(self, s: np.ndarray, y: np.ndarray, guard: float = 1e-10) -> None:
        """Keeps a pair of positive curvature; others, and empty steps, are passed over."""
        s, y = s.ravel(), y.ravel()
        if s @ y > guard * (s @ s) and s @ s > 0:
            self.s, self.y = [*self.s, s][-self.size :], [*self.y, y][-self.size :]

    def apply(self, u: np.ndarray) -> np.ndarray:
        """B u by the compact direct form; 0 with no pair."""
        if not self.s or not self.size:
            return np.zeros_like(u)
        s, y, flat = np.array(self.s).T, np.array(self.y).T, u.ravel()
        sy = s.T @ y
        scale = sy[-1, -1] / (s[:, -1] @ s[:, -1])
        low = np.tril(sy, -1)
        middle = np.block([[scale * s.T @ s, low], [low.T, -np.diag(np.diag(sy))]])
        side = np.concatenate([scale * s.T @ flat, y.T @ flat])
        try:
            inner = np.linalg.solve(middle, side)
        except np.linalg.LinAlgError:
            return (scale * flat).reshape(u.shape)
        return (scale * flat - np.hstack([scale * s, y]) @ inner).reshape(u.shape)


@dataclass
class Edits:
    """Removed rows as they were or added rows as they are now; the driver holds them (at most the budget)."""

    ids: np.ndarray
    x: np.ndarray
    y: np.ndarray
    weight: np.ndarray

    @staticmethod
    def none(classes: int, dims: int) -> Edits:
        return Edits(np.empty(0, np.int64), np.empty((0, dims)), np.empty((0, classes)), np.empty(0))

    def part(self, w: np.ndarray, batch: tuple[int, int, int]) -> tuple[np.ndarray, int]:
        m = batch_of(self.ids, batch[0], batch[2]) == batch[1]
        return gradient_of(self.x[m], self.y[m], self.weight[m], w), int(m.sum())


def replay(rows, trace: list[Step], removed: Edits, added: Edits, cfg: CleanConfig, curvature: str = "lbfgs") -> tuple[np.ndarray, list[Step], int]:
    """(parameters, new trace, explicit steps) of the path on edited data; ``rows`` are the unedited ones.

    The path has the cached number of steps. With nothing edited it is the cached path.
    ``curvature="none"`` leaves the shift out, as an ablation.
    """
    if not trace:
        raise ValueError("there is no path to replay")
    w, memory, out, explicit = trace[0].w.copy(), CurvatureMemory(cfg.history), [], 0
    keys = [(*divmod(t, cfg.batches), cfg.batches) for t in range(len(trace))]
    planned = [t < cfg.burn_in or (t - cfg.burn_in) % cfg.period == 0 for t in range(len(trace))]
    read = rows.each_batch([k for k, p in zip(keys, planned) if p])
    for old, batch, now in zip(trace, keys, planned):
        part = next(read) if now else None
        shift = w - old.w
        if not shift.any():
            whole = old.g
        elif now:
            whole, _ = gradient(part, w, cfg.lam)
            memory.add(shift, whole - old.g)
            explicit += 1
        else:
            whole = old.g + (memory.apply(shift) if curvature == "lbfgs" else 0.0)
        less, n_less = removed.part(w, batch)
        more, n_more = added.part(w, batch)
        n = old.n - n_less + n_more
        penalty = cfg.lam * w
        if n_less or n_more:
            g = ((whole - penalty) * old.n - less + more) / n + penalty if n else penalty
        else:
            g = whole
        out.append(Step(w, g, n))
        w = w - cfg.rate * g
    return w, out, explicit


def replay_label_edits(rows, trace: list[Step], ids, x, old_y, new_y, cfg: CleanConfig, curvature: str = "lbfgs"):
    """Replay where rows change label and weight: out at gamma with the old label, in at 1 with the new one."""
    removed = Edits(ids, x, old_y, np.full(len(ids), cfg.gamma))
    added = Edits(ids, x, new_y, np.ones(len(ids)))
    return replay(rows, trace, removed, added, cfg, curvature)


def retrain(rows, cfg: CleanConfig, steps: int | None = None) -> tuple[np.ndarray, list[Step]]:
    return train_sgd(rows, cfg, steps)


def warm_refit(rows, cfg: CleanConfig, w: np.ndarray, steps: int) -> tuple[np.ndarray, list[Step]]:
    """A few steps of descent on the edited rows from the parameters so far, instead of a refit from zero."""
    return train_sgd(rows, cfg, steps, start=w)


def closeness(w: np.ndarray, reference: np.ndarray, before: np.ndarray, rows) -> dict[str, float]:
    """Distance to the reference, relative to its size and to the move from ``before``; share of equal predictions."""
    same = lambda x, y, g: np.array([((x @ w.T).argmax(axis=1) == (x @ reference.T).argmax(axis=1)).sum()])
    gap = float(np.sqrt(((w - reference) ** 2).sum()))
    return {
        "rel_size": gap / max(float(np.sqrt((reference**2).sum())), 1e-300), "rel_move": gap / max(float(np.sqrt(((before - reference) ** 2).sum())), 1e-300),
        "agree": float(np.ravel(rows.total(same)[0])[0]) / rows.size if rows.size else 1.0,
    }
