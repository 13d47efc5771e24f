"""Cardinality from a register array's harmonic sum and its number of empty registers."""

from __future__ import annotations

import math

from pyspark.sql import Column
from pyspark.sql import functions as F


def alpha(m: int) -> float:
    """Bias constant of the estimator for 256 registers and more."""
    if m < 256:
        raise ValueError("the constant holds from 256 registers on")
    return 0.7213 / (1 + 1.079 / m)


def raw_estimate(z: Column, m: int) -> Column:
    return F.lit(alpha(m) * m * m) / z


def corrected_estimate(z: Column, v: Column, m: int) -> Column:
    """Linear counting where the raw value is at most 2.5 m and registers are empty. 64-bit hashes need no correction above."""
    raw = raw_estimate(z, m)
    return F.when((raw <= 2.5 * m) & (v > 0), F.lit(float(m)) * F.log(F.lit(float(m)) / v)).otherwise(raw)


def estimate_registers(regs, m: int) -> float:
    """The same for a sequence of m register values."""
    z = sum(2.0**-int(r) for r in regs)
    v = sum(1 for r in regs if not r)
    raw = alpha(m) * m * m / z
    return m * math.log(m / v) if raw <= 2.5 * m and v else raw


def reference_error(m: int) -> float:
    """Standard relative error that the estimator's analysis gives."""
    return 1.04 / math.sqrt(m)


def sql_estimate(z: str, v: str, m: int) -> str:
    raw = f"({alpha(m) * m * m!r}::DOUBLE / ({z}))"
    return f"CASE WHEN {raw} <= {2.5 * m} AND ({v}) > 0 THEN {float(m)}::DOUBLE * ln({float(m)}::DOUBLE / ({v})) ELSE {raw} END"
