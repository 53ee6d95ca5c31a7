"""The SQL surface: scalar functions that Catalyst inlines, table functions, and Arrow functions."""

from __future__ import annotations

import numpy as np
import pandas as pd
from pyspark.sql import SparkSession
from pyspark.sql.functions import pandas_udf, udtf
from pyspark.sql.types import ArrayType, DoubleType

_SQL = {
    "wave_lambda(omega DOUBLE, c2 DOUBLE) RETURNS DOUBLE": "2 * (1 - cos(omega)) / c2",
    "wave_omega(lam DOUBLE, c2 DOUBLE) RETURNS DOUBLE": "acos((2 - c2 * lam) / 2)",
    "wave_horizon(lam2 DOUBLE, c2 DOUBLE, eta DOUBLE) RETURNS DOUBLE": "2 * pi() * eta / acos((2 - c2 * lam2) / 2)",
    "wave_u0(id BIGINT, seed BIGINT) RETURNS DOUBLE": (
        "pmod(pmod(pmod(pmod(id, 2147483647L) * 48271L + seed * 16807L + 12345L, 2147483647L) * "
        "pmod(pmod(id, 2147483647L) * 48271L + seed * 16807L + 12345L, 2147483647L), 2147483647L) + "
        "7919L * pmod(id, 2147483647L), 2147483647L) / 2147483647D"
    ),
}


@udtf(returnType="src: bigint, dst: bigint, w: double")
class RingEdges:
    """Both directions of a ring of n nodes."""

    def eval(self, n: int):
        for i in range(n):
            yield i, (i + 1) % n, 1.0
            yield (i + 1) % n, i, 1.0


@udtf(returnType="src: bigint, dst: bigint, w: double")
class LineEdges:
    """Both directions of a line 1..n with one weak link."""

    def eval(self, n: int, weak_at: int, weak: float):
        for i in range(1, n):
            w = weak if i == weak_at else 1.0
            yield i, i + 1, w
            yield i + 1, i, w


@udtf(returnType="bin: int, omega: double, re: double, im: double, power: double")
class SpectrumRows:
    """The spectrum of one series, one row per bin."""

    def eval(self, series: list):
        x = np.asarray(series, dtype=float)
        if len(x):
            z = np.fft.rfft(x) * np.exp(-2j * np.pi * np.arange(len(x) // 2 + 1) / len(x))
            for b, c in enumerate(z):
                yield b, 2 * np.pi * b / len(x), float(c.real), float(c.imag), float(abs(c) ** 2)


@pandas_udf(ArrayType(DoubleType()))
def fft_power(series: pd.Series) -> pd.Series:
    """Power at each bin of each series."""
    return series.map(lambda x: (np.abs(np.fft.rfft(np.asarray(x, dtype=float))) ** 2).tolist() if x is not None else None)


def register(spark: SparkSession) -> None:
    """Make all of them known to ``spark.sql``."""
    for head, body in _SQL.items():
        spark.sql(f"CREATE OR REPLACE TEMPORARY FUNCTION {head} RETURN {body}")
    spark.udtf.register("ring_edges", RingEdges)
    spark.udtf.register("line_edges", LineEdges)
    spark.udtf.register("spectrum_rows", SpectrumRows)
    spark.udf.register("fft_power", fft_power)
