"""One run's settings."""

from __future__ import annotations

from dataclasses import dataclass, replace


@dataclass(frozen=True)
class RunSpec:
    run_id: str = "run"
    seed: int = 42
    n_clients: int = 10
    fraction: float = 0.5
    rounds: int = 200
    epochs: int = 1
    batch_size: int | None = 64
    lr: float = 0.5
    server_lr: float | str = 1.0  # 'literal': the local rate once more
    partition: str = "quota"  # quota, hashed, iid, column
    beta: float = 0.1
    link_mode: str = "static"  # static, per_round, trace
    v_mbit: float = 357.0
    payload_factor: float = 2.0
    dense_fallback: bool = False
    compressor: str = "topk"  # none, topk, randomk, threshold, quantize, sign
    tau: float = 0.01
    bits: int = 8
    scope: str = "global"  # or layer
    error_feedback: bool = False
    base_ratio: float = 0.1
    schedule: str = "uniform"  # or paced
    clamp: bool = True
    weighting: str = "samples"  # or uniform
    coef: str = "share"  # or adjusted
    norm: str = "sum"
    alpha: float = 0.3
    renormalize: bool = False
    gamma: float = 1.0
    max_degree: int = 1
    model: str = "softmax"
    hidden: int = 16
    target_accuracy: float | None = None
    eval_every: int = 1
    eval_share: float = 1.0  # of the test rows, by hash; metrics.accuracy_interval gives the error

    @property
    def step_size(self) -> float:
        return self.lr if self.server_lr == "literal" else float(self.server_lr)

    def cohort(self) -> tuple:
        """Runs with the same cohort share samples, clients, order and model, and so train in the same jobs."""
        return (self.seed, self.n_clients, self.fraction, self.rounds, self.epochs, self.batch_size, self.lr, self.partition, self.beta, self.model, self.hidden)


PACED = {"schedule": "paced", "coef": "adjusted"}
METHODS = {
    "dense": {"compressor": "none"},
    "topk": {},
    "ef_topk": {"error_feedback": True},
    "paced": PACED,
    "boosted": PACED | {"gamma": 5.0},
    "boost_only": {"gamma": 5.0},
    "pace_only": {"schedule": "paced"},
    "coef_only": {"coef": "adjusted"},
    "ef_boosted": PACED | {"gamma": 5.0, "error_feedback": True},
    "randomk": {"compressor": "randomk"},
    "randomk_boosted": PACED | {"compressor": "randomk", "gamma": 5.0},
    "quantize": {"compressor": "quantize"},
    "sign": {"compressor": "sign"},
    "threshold": {"compressor": "threshold"},
    "topk_layer": {"scope": "layer"},
}


def method(name: str, **changes) -> RunSpec:
    """A named method's settings; run_id defaults to the name."""
    return replace(RunSpec(run_id=name, **METHODS[name]), **changes)
