"""Parameters of a factorisation, and stop rules."""

from __future__ import annotations

import json
from dataclasses import asdict, dataclass


@dataclass(frozen=True)
class MFParams:
    """k: latent columns. gamma: step. lam_p, lam_q: penalties. epochs: passes.

    q_sees: whether the column step uses the row vector before ('old_p') or after ('new_p') its own step.
    grad_scale: 1, or 2 if the factor of the derivative is kept.
    """

    k: int = 8
    gamma: float = 0.01
    lam_p: float = 0.05
    lam_q: float = 0.05
    epochs: int = 2
    q_sees: str = "old_p"
    grad_scale: float = 1.0
    seed: int = 1
    scale: float = 1.0
    batch_width: int = 128
    collide: str = "sum"

    def to_json(self) -> str:
        return json.dumps(asdict(self))

    @staticmethod
    def from_json(text: str) -> MFParams:
        return MFParams(**json.loads(text))


class Stop:
    """stop(trace) -> bool, trace = list of dicts with epoch, rmse_test, wall_s."""

    def __call__(self, trace: list[dict]) -> bool:
        raise NotImplementedError


@dataclass(frozen=True)
class FixedEpochs(Stop):
    epochs: int

    def __call__(self, trace):
        return len(trace) >= self.epochs


@dataclass(frozen=True)
class TargetRMSE(Stop):
    target: float

    def __call__(self, trace):
        return bool(trace) and trace[-1]["rmse_test"] is not None and trace[-1]["rmse_test"] <= self.target


@dataclass(frozen=True)
class RelChange(Stop):
    eps: float

    def __call__(self, trace):
        if len(trace) < 2:
            return False
        a, b = trace[-2]["rmse_test"], trace[-1]["rmse_test"]
        return a is not None and b is not None and abs(a - b) <= self.eps * a


class AnyOf(Stop):
    def __init__(self, *rules: Stop):
        self.rules = rules

    def __call__(self, trace):
        return any(r(trace) for r in self.rules)
