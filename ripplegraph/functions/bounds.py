"""Speed limits, eigenvalue relations, horizons and rates: scalar columns, folded or computed inside a scan."""

from __future__ import annotations

import math

from pyspark.sql import Column, DataFrame, SparkSession
from pyspark.sql import functions as F

DEFAULT_C2 = 1.99


def _col(x: Column | float | str) -> Column:
    return x if isinstance(x, Column) else F.col(x) if isinstance(x, str) else F.lit(float(x))


def speed_limit(lambda_max: float | None = None) -> float:
    """Largest squared speed that is stable: below 2 on any graph, up to 4 / lambda_max on one."""
    return 2.0 if lambda_max is None else 4.0 / lambda_max


def check_speed(c2: float, lambda_max: float | None = None) -> float:
    limit = speed_limit(lambda_max)
    if not 0 < c2 < limit:
        raise ValueError(f"squared wave speed {c2} is outside (0, {limit})")
    return c2


def omega_of(lam: Column | float | str, c2: Column | float) -> Column:
    """Frequency of an eigenvalue."""
    return F.acos((2 - _col(c2) * _col(lam)) / 2)


def lambda_of(omega: Column | float | str, c2: Column | float) -> Column:
    """Eigenvalue of a frequency."""
    return 2 * (1 - F.cos(_col(omega))) / _col(c2)


def companion(lam: Column | str, c2: Column | float) -> Column:
    """The two roots that belong to an eigenvalue, as a struct: re, im (of the upper root), modulus of the larger, phase."""
    b = 2 - _col(c2) * _col(lam)
    disc = b * b - 4
    real = disc >= 0
    root = F.sqrt(F.abs(disc))
    re = F.when(real, (b + F.signum(b) * root) / 2).otherwise(b / 2)
    im = F.when(real, F.lit(0.0)).otherwise(root / 2)
    return F.struct(re.alias("re"), im.alias("im"), F.sqrt(re * re + im * im).alias("modulus"), F.atan2(im, re).alias("phase"))


def growth_cases(eigenvalues: DataFrame, c2: float) -> DataFrame:
    """Which of the three critical cases occur among ``eigenvalues(lam)``: constant mode, repeated value, alternating mode."""
    rounded = eigenvalues.select(F.round("lam", 9).alias("lam")).groupBy("lam").agg(F.count("*").alias("times"))
    return rounded.agg(
        F.max(F.when(F.abs("lam") < 1e-9, True).otherwise(False)).alias("constant_mode"),
        F.max(F.col("times") > 1).alias("repeated"),
        F.max((F.abs(F.col("lam") - 2) < 1e-9) & F.lit(c2 >= 2)).alias("alternating_mode"),
    )


def mixing_time(lam2: Column | float | str, kind: str = "second", lam_max: Column | float | str | None = None) -> Column:
    """-1 / ln of the walk's second factor: 1 - lam2, the larger modulus of both ends, or the lazy walk's."""
    if kind == "lazy":
        factor = 1 - _col(lam2) / 2
    elif kind == "slem":
        factor = F.greatest(F.abs(1 - _col(lam2)), F.abs(1 - _col(lam_max)))
    else:
        factor = F.abs(1 - _col(lam2))
    return -1 / F.log(factor)


def omega_from_mixing(tau: Column | float | str, c2: Column | float) -> Column:
    return F.acos((2 + _col(c2) * (F.exp(-1 / _col(tau)) - 1)) / 2)


def wave_horizon(omega2: Column, eta: float = 6.5, rule: str = "cycles", gather_nodes: Column | float = 0) -> Column:
    """Steps for ``eta`` cycles of the lowest frequency; ``printed`` omits the factor two pi; plus the gather of N nodes."""
    return F.lit(eta * (2 * math.pi if rule == "cycles" else 1.0)) / omega2 + _col(gather_nodes)


def asymptotic_steps(tau: Column | float | str, c2: Column | float) -> Column:
    return F.sqrt(_col(tau)) / F.sqrt(_col(c2))


def resolution_steps(omega_a: Column, omega_b: Column) -> Column:
    """Samples needed to tell two frequencies apart."""
    return 1 / F.abs(omega_a - omega_b)


def walk_cost(tau: Column | float | str, n: Column | float | str) -> Column:
    """Rounds of the random-walk based eigenvector computation."""
    return _col(tau) * F.pow(F.log2(_col(n)), F.lit(2.0))


def ring(n: Column | str, c2: float = DEFAULT_C2, eta: float = 6.5) -> list[Column]:
    """Closed forms of a ring of n nodes: lambda2, mixing time exact and in its two approximations, steps exact and for large n."""
    turn = 2 * math.pi / _col(n)
    lam = 1 - F.cos(turn)
    quarter = F.pow(_col(n) / (2 * math.pi), F.lit(2.0))
    return [
        lam.alias("lambda2"), (-1 / F.log(F.cos(turn))).alias("tau"), quarter.alias("tau_printed"), (2 * quarter).alias("tau_series"),
        (F.lit(eta) / omega_of(lam, c2)).alias("steps"), (F.lit(eta) * _col(n) / (math.sqrt(2 * c2) * math.pi)).alias("steps_large"),
    ]


def compare(spark: SparkSession, taus: list[float], sizes: list[int], c2: float = DEFAULT_C2, eta: float = 6.5) -> DataFrame:
    """Wave steps against walk rounds over mixing times and sizes."""
    grid = spark.createDataFrame([(float(t),) for t in taus], "tau double").crossJoin(F.broadcast(spark.createDataFrame([(n,) for n in sizes], "n long")))
    wave = F.lit(eta) / omega_from_mixing("tau", c2)
    return grid.select("tau", "n", wave.alias("wave_steps"), (wave + F.col("n")).alias("wave_with_gather"), walk_cost("tau", "n").alias("walk_rounds"), asymptotic_steps("tau", c2).alias("wave_large_tau"))
