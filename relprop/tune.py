"""Random search over learning rate, decay and dropout, by validation."""

from __future__ import annotations

from concurrent.futures import ThreadPoolExecutor
from dataclasses import dataclass

import numpy as np

from .schema import Task
from .train import Fit, run

#: The protocol: fixed values.
TRIALS, RERUNS, WIDTH, GNN_WIDTH = 50, 5, 16, 64
LOG_RANGE = (1e-7, 1e-3)
DROPOUT = {"transformer": 0.3, "other": 0.2}


@dataclass
class Trial:
    rate: float
    decay: float
    dropout: float
    valid: float = float("nan")


def sample(block: str, trials: int = TRIALS, seed: int = 0, log_range: tuple[float, float] = LOG_RANGE) -> list[Trial]:
    """Rate and decay log-uniform, dropout uniform up to the block's bound."""
    rng = np.random.default_rng(seed)
    lo, hi = np.log(log_range[0]), np.log(log_range[1])
    top = DROPOUT.get(block, DROPOUT["other"])
    return [Trial(float(np.exp(rng.uniform(lo, hi))), float(np.exp(rng.uniform(lo, hi))), float(rng.uniform(0, top))) for _ in range(trials)]


def search(task: Task, method: str, depth: int, trials: list[Trial], epochs: int = 10, threads: int = 1, **more) -> Trial:
    """The trial that does best on the validation part; trials run in threads of the driver."""

    def one(t: Trial) -> Trial:
        trained, _, packed = run(task, method, depth, Fit(epochs=epochs, rate=t.rate, decay=t.decay), dropout=t.dropout, **more)
        packed.unpersist()
        t.valid = max((h[2] for h in trained.history), default=float("nan"))
        return t

    with ThreadPoolExecutor(threads) as pool:
        done = list(pool.map(one, trials))
    return max(done, key=lambda t: -np.inf if np.isnan(t.valid) else t.valid)
