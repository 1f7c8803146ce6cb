"""Cost of each method in operations and bytes, and the choice between methods."""

from __future__ import annotations

from dataclasses import dataclass

METHODS = ("retrain", "replay", "replay_lowrank", "replay_sparse", "spectral", "normal_eq", "influence")


@dataclass(frozen=True)
class Stats:
    """n rows, m features, q classes, batch size, iterations, removed rows, rank, non-zeros a row (0: dense)."""

    n: int
    m: int
    batch: int
    tau: int
    removed: int
    kind: str = "linear"
    q: int = 1
    rank: int | None = None
    nonzeros: float = 0.0
    switch: float = 0.7
    exp_cost: float = 10.0

    @property
    def size(self) -> int:
        return self.m * (self.q if self.kind == "softmax" else 1)

    @property
    def removed_in_batch(self) -> float:
        return self.removed * self.batch / max(self.n, 1)


def cost(s: Stats) -> dict[str, dict[str, float]]:
    """{method: {online, offline, bytes}}: operations after and before the removal is known, and provenance kept."""
    p, b, db = s.size, s.batch, s.removed_in_batch
    r = s.rank if s.rank is not None else min(b, p)
    blocks = min(s.tau, -(-s.n // max(b, 1))) if s.kind == "linear" else s.tau
    nonlinear = 0.0 if s.kind == "linear" else s.exp_cost * (s.q if s.kind == "softmax" else 1)
    coefficients = 0.0 if s.kind == "linear" else 16.0 * s.tau * b
    diag = min(s.removed, p) * p * p
    head = s.switch * s.tau if s.kind != "linear" else 0.0
    out = {
        "retrain": {"online": s.tau * ((b - db) * p + nonlinear * (b - db)), "offline": 0.0, "bytes": 0.0},
        "replay": {"online": s.tau * (db * p + p * p), "offline": blocks * b * p * p, "bytes": 8.0 * blocks * p * p + coefficients},
        "replay_lowrank": {"online": s.tau * (r * p + db * p), "offline": blocks * min(p, b) * b * p, "bytes": 16.0 * blocks * r * p + coefficients},
        "spectral": {"online": diag + head * (r * p + db * p) + (s.tau - head) * p, "offline": s.n * p * p + p**3 + head * b * p * p, "bytes": 8.0 * (p * p + head * 2 * r * p) + (0.7 if coefficients else 0) * coefficients},
        "influence": {"online": s.removed * p + p * p, "offline": s.n * p * p + p**3, "bytes": 8.0 * p * p},
    }
    if s.kind == "linear":
        out["normal_eq"] = {"online": diag + p**3, "offline": s.n * p * p, "bytes": 8.0 * p * p}
    if s.nonzeros:
        out["replay_sparse"] = {"online": s.tau * (b - db) * s.nonzeros, "offline": s.tau * b * s.nonzeros, "bytes": coefficients}
    return out


def choose(s: Stats, small: int = 512, heavy: float = 0.2, max_dense: int = 2048) -> str:
    """The method for an exact-in-the-limit update: sparse rows replay directly, few features go spectral, many go low-rank.

    Near ``heavy`` removal the first-order eigenvalues lose their edge and
    replay is taken; if even that costs more than retraining, retraining is.
    """
    if s.nonzeros:
        return "replay_sparse"
    costs = cost(s)
    rate = s.removed / max(s.n, 1)
    if s.size <= small and rate < heavy:
        best = "spectral"
    else:
        best = "replay_lowrank" if s.size > max_dense or (s.rank or s.size) * 2 < s.size else "replay"
    return best if costs[best]["online"] < costs["retrain"]["online"] else "retrain"


def step_bound(largest: float, n: int, kind: str, lam: float) -> float:
    """Largest admissible rate: the inverse of the gradient's Lipschitz constant, from the top eigenvalue of X'X."""
    scale = {"linear": 2.0, "binary": 0.25, "softmax": 0.5}[kind]
    return 1.0 / (scale * largest / n + lam)
