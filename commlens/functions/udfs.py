"""Functions that built-ins cannot express: exact augmentation draws, log-gamma, aggregates and table functions, all on Arrow batches."""

from __future__ import annotations

import math

import numpy as np
import pandas as pd
from pyspark.sql import Column, SparkSession
from pyspark.sql.functions import pandas_udf, udtf
from pyspark.sql.types import DoubleType

from commlens.functions.augmentation import KeyedRandom, pg_exact, pg_series


def _lgamma(x: np.ndarray) -> np.ndarray:
    """Stirling's series after a shift to arguments of ten and more."""
    x = np.asarray(x, dtype=float)
    shift = np.zeros_like(x)
    y = x.copy()
    while (low := y < 10).any():
        shift[low] += np.log(y[low])
        y[low] += 1
    inv = 1 / y
    sq = inv * inv
    series = inv * (1 / 12 - sq * (1 / 360 - sq * (1 / 1260 - sq * (1 / 1680 - sq / 1188))))
    return (y - 0.5) * np.log(y) - y + 0.5 * math.log(2 * math.pi) + series - shift


@pandas_udf(DoubleType())
def lgamma_udf(x: pd.Series) -> pd.Series:
    return pd.Series(_lgamma(x.to_numpy()))


def pg_draw(b: Column, key: Column, salt: int = 0, mode: str = "exact") -> Column:
    """PG(1, b) draws, repeatable by key and salt."""

    @pandas_udf(DoubleType())
    def draw(scores: pd.Series, keys: pd.Series) -> pd.Series:
        rng = KeyedRandom(keys.to_numpy(), salt)
        return pd.Series((pg_exact if mode == "exact" else pg_series)(scores.to_numpy(dtype=float), rng))

    return draw(b, key)


@pandas_udf(DoubleType())
def auc_udaf(score: pd.Series, label: pd.Series) -> float:
    """AUC within a group (small groups; ``measures.auc`` is the scalable form)."""
    rank = score.rank().to_numpy()
    y = label.to_numpy() == 1
    n = int(y.sum())
    return float((rank[y].sum() - n * (n + 1) / 2) / (n * (len(y) - n))) if 0 < n < len(y) else float("nan")


@pandas_udf(DoubleType())
def logsumexp_udaf(x: pd.Series) -> float:
    m = x.max()
    return float(m + np.log(np.exp(x - m).sum()))


@udtf(returnType="pos int, token string")
class Tokenize:
    """Words of a text with their places."""

    def eval(self, text: str):
        for i, w in enumerate((text or "").lower().split()):
            yield i, w


@udtf(returnType="end string, id bigint")
class ExpandLink:
    """Both ends of a link."""

    def eval(self, src: int, dst: int):
        yield "src", src
        yield "dst", dst


def register(spark: SparkSession) -> None:
    spark.udtf.register("tokenize", Tokenize)
    spark.udtf.register("expand_link", ExpandLink)
    spark.udf.register("lgamma_udf", lgamma_udf)


def log_gamma(x: Column) -> Column:
    return lgamma_udf(x.cast("double"))


__all__ = ["ExpandLink", "Tokenize", "auc_udaf", "lgamma_udf", "log_gamma", "logsumexp_udaf", "pg_draw", "pg_exact", "pg_series", "register"]
