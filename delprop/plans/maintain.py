"""A trained model kept up to date: what to hold is settled after training, the method when a removal arrives.

:func:`maintain` trains and captures what :func:`planner.choose` may ask for;
:func:`update` counts the removed rows, lets the planner choose among retraining,
replay (dense, low-rank, sparse) and the spectral update, and applies its choice.
"""

from __future__ import annotations

from dataclasses import dataclass, field

import numpy as np
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from delprop.operators import capture, replay, sparse, spectral, train
from delprop.operators.capture import Capture
from delprop.plans import planner
from delprop.spec import ModelSpec


@dataclass
class Maintained:
    """A model and its provenance; parts that the planner never asks for at this size stay empty."""

    spec: ModelSpec
    n: int
    w: np.ndarray
    sums: Capture | None = None
    eigen: spectral.Eigen | spectral.LogisticSpectral | None = None
    coefficients: dict = field(default_factory=dict)
    nonzeros: float = 0.0

    def stats(self, removed: int) -> planner.Stats:
        spec = self.spec
        batch = -(-self.n // max(spec.blocks(self.n), 1)) if spec.batch_size is None else spec.batch_size
        return planner.Stats(max(self.n, 1), spec.m, batch, spec.tau, removed, spec.kind, spec.q, nonzeros=self.nonzeros)


@dataclass
class Updated:
    """Parameters after a removal, the method that gave them and the number of rows that it removed."""

    w: np.ndarray
    method: str
    removed: int


def maintain(samples: DataFrame, spec: ModelSpec, small: int = 512, eps: float = 0.01) -> Maintained:
    """Train, and capture by size: sparse rows keep coefficients, up to ``small`` parameters sums and eigenvectors, more sums, beyond dense orders factors to within ``eps``.

    Sparse rows (columns ``indices`` and ``values``) are told by their columns.  ``samples`` is read several times.
    """
    n = samples.count()
    if "indices" in samples.columns:
        held: dict = {}
        w = sparse.train(samples, spec, n, held)
        return Maintained(spec, n, w, coefficients=held, nonzeros=float(samples.agg(F.avg(F.size("indices"))).first()[0] or 1.0))
    fit = train.train(samples, spec, n, keep_trajectory=spec.kind != "linear")
    if spec.size > capture.MAX_DENSE:
        return Maintained(spec, n, fit.w, capture.capture_factors(samples, spec, n, None if spec.kind == "linear" else fit.trajectory, eps))
    if spec.kind == "linear":
        return Maintained(spec, n, fit.w, capture.capture_linear(samples, spec, n), spectral.fit_eigen(samples, spec) if spec.size <= small else None)
    sums = capture.capture_logistic(samples, fit.trajectory, spec, n)
    return Maintained(spec, n, fit.w, sums, spectral.fit_logistic(samples, sums, spectral.switch_point(spec)) if spec.size <= small else None)


def update(kept: Maintained, samples: DataFrame, removals: DataFrame, small: int = 512) -> Updated:
    """The model without ``removals`` (ids that do not exist do nothing), by the method the planner chooses for their number."""
    spec = kept.spec
    ids = removals.select("sample_id").distinct()
    removed = samples.join(ids, "sample_id", "left_semi").count()
    method = planner.choose(kept.stats(removed), small, max_dense=capture.MAX_DENSE)
    if method == "replay_sparse":
        w = sparse.replay(samples, ids, spec, kept.n, kept.coefficients)
    elif method == "retrain":
        w = train.retrain(samples, ids, spec, kept.n).w
    elif method == "spectral" and spec.kind == "linear":
        w = spectral.spectral_linear(kept.eigen, samples, ids, spec)
    elif method == "spectral":
        w = spectral.spectral_logistic(kept.eigen, samples, ids)
    else:
        w = replay.replay(kept.sums, samples, ids)
    return Updated(w, method, removed)
