"""Column expressions of the model; all stay inside generated code."""

from __future__ import annotations

from pyspark.sql import Column, SparkSession
from pyspark.sql import functions as F

#: Modulus and multipliers of the counter-based uniforms (fixed values, shared with the oracles).
MODULUS, FIRST, SECOND = 2147483647, 48271, 16807


def sigmoid(x: Column) -> Column:
    return 1.0 / (1.0 + F.exp(-x))


def log_psi(w: Column, x: Column) -> Column:
    """Log of the Gaussian factor that stands for a sigmoid given its augmentation variable x."""
    return (w - x * w * w) / 2.0


def pg_mean(b: Column) -> Column:
    """Mean of the Polya-Gamma law PG(1, b), with its limit a quarter at zero."""
    return F.when(F.abs(b) < 1e-6, F.lit(0.25)).otherwise(F.tanh(b / 2.0) / (2.0 * b))


def hashed(key: Column, salt: int) -> Column:
    """A whole number from 0 to MODULUS - 1 that depends on nothing but key and salt: retries and other partitions give the same."""
    return F.pmod(F.pmod(key.cast("bigint") * FIRST + salt, F.lit(MODULUS)) * SECOND, F.lit(MODULUS))


def uniform(key: Column, salt: int) -> Column:
    """A number strictly between 0 and 1, by a linear hash that other engines can repeat."""
    return (hashed(key, salt).cast("double") + 0.5) / float(MODULUS)


def noise(salt: int, *keys: Column) -> Column:
    """A number strictly between 0 and 1, well mixed over keys and salt; the sampler's default."""
    return (F.shiftrightunsigned(F.xxhash64(*keys, F.lit(salt)), 11).cast("double") + 0.5) / float(1 << 53)


def log_rising(start: Column, n: Column) -> Column:
    """ln of start * (start + 1) * ... with n factors."""
    return F.when(n > 0, F.aggregate(F.sequence(F.lit(0), n.cast("int") - 1), F.lit(0.0), lambda acc, i: acc + F.ln(start + i))).otherwise(F.lit(0.0))


def log_rising_ratio(count: Column, prior: float, n: Column) -> Column:
    """log_rising(count + prior, n) - log_rising(prior, n), zero where count is: only non-zero cells need to be joined."""
    return F.when(n > 0, F.aggregate(F.sequence(F.lit(0), n.cast("int") - 1), F.lit(0.0), lambda acc, i: acc + F.ln(1.0 + count / (F.lit(prior) + i)))).otherwise(F.lit(0.0))


def register(spark: SparkSession) -> None:
    """SQL functions of the same names, for users who write SQL."""
    spark.sql("CREATE OR REPLACE TEMPORARY FUNCTION sigmoid(x DOUBLE) RETURNS DOUBLE RETURN 1D / (1D + exp(-x))")
    spark.sql("CREATE OR REPLACE TEMPORARY FUNCTION log_psi(w DOUBLE, x DOUBLE) RETURNS DOUBLE RETURN (w - x * w * w) / 2D")
    spark.sql("CREATE OR REPLACE TEMPORARY FUNCTION pg_mean(b DOUBLE) RETURNS DOUBLE RETURN CASE WHEN abs(b) < 1e-6D THEN 0.25D ELSE tanh(b / 2D) / (2D * b) END")
