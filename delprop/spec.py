"""What a model is and how it is trained."""

from __future__ import annotations

from collections.abc import Sequence
from dataclasses import dataclass, replace

import numpy as np

KINDS = ("linear", "binary", "softmax")
SCHEDULES = ("full", "cyclic", "reshuffle", "sampled", "single")


@dataclass(frozen=True)
class ModelSpec:
    """An L2-regularised regression model and its gradient schedule.

    ``m`` counts features, the explicit intercept included; ``q`` counts
    classes (softmax only).  Labels: any double (linear), -1 or 1 (binary),
    0..q-1 (softmax).  Training starts at ``w0``, or at zero.
    """

    kind: str
    m: int
    q: int = 1
    lam: float = 0.1
    eta: float | Sequence[float] = 5e-3
    tau: int = 100
    batch_size: int | None = None
    schedule: str = "full"
    seed: str = "batch"
    w0: tuple[float, ...] | None = None
    penalty: str = "l2"

    def __post_init__(self) -> None:
        if self.penalty != "l2":
            raise ValueError("only the L2 penalty keeps the update rule linear in the samples; L1 is not supported")
        if self.kind not in KINDS or self.schedule not in SCHEDULES:
            raise ValueError(f"kind must be one of {KINDS} and schedule one of {SCHEDULES}")
        if self.schedule in ("cyclic", "reshuffle", "sampled") and not self.batch_size:
            raise ValueError(f"schedule {self.schedule} needs a batch_size")
        if not np.isscalar(self.eta) and len(self.eta) < self.tau:
            raise ValueError("a list of learning rates needs one rate an iteration")
        if self.kind == "softmax" and self.q < 2:
            raise ValueError("softmax needs q >= 2")

    @property
    def size(self) -> int:
        """Length of the parameter vector; softmax stacks its classes."""
        return self.m * (self.q if self.kind == "softmax" else 1)

    def rate(self, t: int) -> float:
        return float(self.eta if np.isscalar(self.eta) else self.eta[t])

    def start(self) -> np.ndarray:
        return np.zeros(self.size) if self.w0 is None else np.array(self.w0, float)

    def batches(self, n: int) -> int:
        """Mini-batches in a pass over ``n`` rows."""
        return 1 if not self.batch_size else max(1, -(-n // self.batch_size))

    def blocks(self, n: int) -> int:
        """Distinct blocks of rows; iteration ``t`` uses block ``t`` modulo this number."""
        k = self.batches(n)
        return {
            "full": 1,
            "cyclic": k,
            "reshuffle": k * -(-self.tau // k),
            "sampled": self.tau,
            "single": max(1, min(n, self.tau)),
        }[self.schedule]

    def with_(self, **changes) -> ModelSpec:
        return replace(self, **changes)
