"""Settings of label cleaning."""

from __future__ import annotations

from dataclasses import dataclass, replace


@dataclass(frozen=True)
class CleanConfig:
    gamma: float = 0.8  # weight of an uncleaned row
    lam: float = 0.05  # L2 on the averaged objective
    classes: int = 2
    budget: int = 20  # rows cleaned in all
    round_size: int = 5  # rows cleaned a round
    rate: float = 0.5
    steps: int = 150
    batches: int = 1  # mini-batches an epoch; 1: full batch
    burn_in: int = 10  # replay: first steps that are explicit
    patience: int = 0  # epochs of rising validation loss that end a training; 0: all steps are made
    warm_steps: int = 15  # steps of a warm refit
    period: int = 20  # replay: every so many steps are explicit
    history: int = 2  # replay: curvature pairs
    strategy: str = "SUGGEST"
    annotator_error: float = 0.05
    brackets: str = "softmax_exact"
    threshold: str = "printed"
    reanchor_at: float = 0.25
    local_bytes: int = 64 << 20  # training sets up to this size are held by the driver

    def __post_init__(self):
        if not 0 < self.gamma <= 1 or self.lam <= 0 or self.round_size < 1 or self.classes < 2:
            raise ValueError("gamma must lie in (0, 1], lam above 0, round_size from 1, classes from 2")

    def but(self, **changes) -> CleanConfig:
        return replace(self, **changes)
