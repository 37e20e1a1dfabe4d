"""What a training run is: one value that determines all its draws and results."""

from __future__ import annotations

import hashlib
import json
from dataclasses import asdict, dataclass, field, replace


@dataclass(frozen=True)
class RunSpec:
    """Defaults are those of the experiments. ``options`` holds settings of single schemes (sample, mean, deadline ...)."""

    scheme: str = "quorum_stop"
    workers: int = 20
    quorum: int = 5
    quota: int = 10
    batch: int = 100
    step_size: float = 0.1
    model: str = "softmax"
    split: str = "even_random"
    mean: float = 1e-4
    seed: int = 0
    rounds: int = 100
    target: float = 0.9
    max_time: float | None = None
    max_messages: int | None = None
    eval_every: int = 1
    options: dict[str, float | str] = field(default_factory=dict)

    def to_json(self) -> str:
        return json.dumps(asdict(self), sort_keys=True)

    @staticmethod
    def from_json(text: str) -> "RunSpec":
        return RunSpec(**json.loads(text))

    @property
    def run_id(self) -> str:
        return hashlib.md5(self.to_json().encode()).hexdigest()

    def but(self, **changes) -> "RunSpec":
        return replace(self, **changes)


def should_stop(spec: RunSpec, row: dict) -> bool:
    """After a round: target accuracy, rounds, simulated time or messages."""
    return bool(
        row["accuracy"] is not None and row["accuracy"] >= spec.target
        or row["round_no"] + 1 >= spec.rounds
        or spec.max_time is not None and row["cum_time"] >= spec.max_time
        or spec.max_messages is not None and row["cum_messages"] >= spec.max_messages
    )
