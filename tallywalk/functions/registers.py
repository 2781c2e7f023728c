"""Estimates of a distinct count from registers.

`histogram` grows whenever a register grows, as the walks need; `classic` switches formulas on its way and can step down there. Both need two numbers of a counter
only: how many registers are empty, and the sum of 2**-value over the others.
"""

from __future__ import annotations

import math
from functools import lru_cache

import numpy as np
from pyspark.sql import Column
from pyspark.sql import functions as F

SERIES = 20  # terms of the small-range correction; more change nothing up to 4096 registers
ESTIMATORS = ("histogram", "classic")
HALVES = np.exp2(-np.arange(256.0))


def alpha(m: int) -> float:
    # fixed values: the classic estimator's bias corrections
    return {16: 0.673, 32: 0.697, 64: 0.709}.get(m, 0.7213 / (1 + 1.079 / m))


def sigma(x: float) -> float:
    """The small-range correction: infinite where all registers are empty."""
    return x + sum(x ** (2.0**k) * 2.0 ** (k - 1) for k in range(1, SERIES + 1))


@lru_cache(maxsize=16)
def sigma_table(m: int) -> np.ndarray:
    return np.array([sigma(v / m) for v in range(m + 1)])


@lru_cache(maxsize=16)
def linear_table(m: int) -> np.ndarray:
    """The classic estimator's other formula, by the number of empty registers."""
    return m * np.log(m / np.maximum(np.arange(m + 1), 1))


def estimate_sums(m: int, empty: np.ndarray, powers: np.ndarray, estimator: str = "histogram") -> np.ndarray:
    """Estimates from the numbers of empty registers and the sums of 2**-value over all of a counter's."""
    if estimator == "histogram":
        out = m * m / (2 * math.log(2)) / (m * sigma_table(m)[empty] + powers - empty)
        return np.where(empty == m, 0.0, out)
    raw = alpha(m) * m * m / powers
    return np.where((raw <= 2.5 * m) & (empty > 0), linear_table(m)[empty], raw)


def estimate_arrays(registers: np.ndarray, estimator: str = "histogram") -> np.ndarray:
    """Estimates of the rows of a register matrix."""
    return estimate_sums(registers.shape[1], (registers == 0).sum(axis=1), HALVES[registers].sum(axis=1), estimator)


def histogram_estimate(m: int, filled: Column, powers: Column) -> Column:
    """From the number of filled registers and the sum of 2**-value over them."""
    x = (F.lit(m) - filled) / F.lit(float(m))
    terms = F.aggregate(F.sequence(F.lit(1), F.lit(SERIES)), x, lambda acc, k: acc + F.pow(x, F.pow(F.lit(2.0), k)) * F.pow(F.lit(2.0), k - 1))
    return F.when(filled == 0, 0.0).otherwise(F.lit(m * m / (2 * math.log(2))) / (F.lit(float(m)) * terms + powers))


def classic_estimate(m: int, filled: Column, powers: Column) -> Column:
    empty = F.lit(m) - filled
    raw = F.lit(alpha(m) * m * m) / (powers + empty)
    return F.when((raw <= 2.5 * m) & (empty > 0), F.lit(float(m)) * F.ln(F.lit(float(m)) / empty)).otherwise(raw)


def estimate_of(estimator: str, m: int, filled: Column, powers: Column) -> Column:
    if estimator not in ESTIMATORS:
        raise ValueError(f"estimator must be one of {ESTIMATORS}")
    return histogram_estimate(m, filled, powers) if estimator == "histogram" else classic_estimate(m, filled, powers)


def estimate_registers(estimator: str = "histogram"):
    """An Arrow function from registers (BINARY, one byte each) to their estimate."""
    import pyarrow as pa

    def run(column: pa.Array) -> pa.Array:
        rows = column.to_pylist()
        got: list[float | None] = [None] * len(rows)
        by_size: dict[int, list[int]] = {}
        for i, r in enumerate(rows):
            if r:
                by_size.setdefault(len(r), []).append(i)
        for m, those in by_size.items():
            matrix = np.frombuffer(b"".join(rows[i] for i in those), np.uint8).reshape(-1, m)
            for i, v in zip(those, estimate_arrays(matrix, estimator).tolist()):
                got[i] = v
        return pa.array(got, pa.float64())

    run.__annotations__ = {}
    return F.arrow_udf(run, "double", functionType=F.ArrowUDFType.SCALAR) if hasattr(F, "ArrowUDFType") else F.arrow_udf(run, "double")


def relative_error(m: int) -> float:
    """The expected relative deviation of an estimate from m registers."""
    return 1.04 / math.sqrt(m)
