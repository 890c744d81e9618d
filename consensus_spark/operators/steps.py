"""Step-size policies as columns of the iteration number."""

from __future__ import annotations

import math
import warnings

from pyspark.sql import Column
from pyspark.sql import functions as F

# Fixed values of the experiments.
FIRST_STEP = 0.2
DECAY = 0.95


def constant(c: float):
    return lambda k, worker=None: F.lit(float(c))


def geometric(c0: float = FIRST_STEP, rate: float = DECAY):
    return lambda k, worker=None: c0 * F.pow(F.lit(rate), k)


def horizon(n: int, last: int, smoothness: float | None = None):
    step = math.sqrt(n / last)
    if smoothness is not None and step * smoothness > 1:
        warnings.warn("the step times the smoothness constant exceeds one", stacklevel=2)
    return lambda k, worker=None: F.lit(step)


def per_worker(steps: dict[int, float]):
    def policy(k: Column, worker: Column) -> Column:
        return F.element_at(F.array(*[F.lit(float(steps[i])) for i in sorted(steps)]), worker + 1)

    return policy


def batch_proportional(c: float):
    """Proportional to the share of the batch that took part."""
    return lambda k, active_rows, total_rows: F.lit(float(c)) * active_rows / total_rows


def value_at(kind: str, k: int, **p) -> float:
    """The same policies as numbers, for the driver loop."""
    if kind == "constant":
        return p["c"]
    if kind == "geometric":
        return p.get("c0", FIRST_STEP) * p.get("rate", DECAY) ** k
    if kind == "horizon":
        return math.sqrt(p["n"] / p["last"])
    raise ValueError(f"no step policy {kind}")
