"""Draws of the augmentation variables, PG(1, b), as array functions. Each row has a stream of random numbers of its own, from its key:
a draw depends on nothing else, so a task that runs again, or batches cut elsewhere, give the same."""

from __future__ import annotations

import math

import numpy as np

_TRUNCATE = 0.64


class KeyedRandom:
    """Uniforms, exponentials and normals for rows by number; row i's k-th number is a hash of its key, the salt and k."""

    def __init__(self, keys: np.ndarray, salt: int) -> None:
        self.state = self._mix(np.asarray(keys).astype(np.int64).view(np.uint64) ^ self._mix(np.array([salt % (1 << 63)], dtype=np.uint64)))

    @staticmethod
    def _mix(x: np.ndarray) -> np.ndarray:
        with np.errstate(over="ignore"):
            x = x + np.uint64(0x9E3779B97F4A7C15)
            x = (x ^ (x >> np.uint64(30))) * np.uint64(0xBF58476D1CE4E5B9)
            x = (x ^ (x >> np.uint64(27))) * np.uint64(0x94D049BB133111EB)
            return x ^ (x >> np.uint64(31))

    def uniform(self, rows: np.ndarray) -> np.ndarray:
        with np.errstate(over="ignore"):
            self.state[rows] += np.uint64(0x9E3779B97F4A7C15)
        return ((self._mix(self.state[rows]) >> np.uint64(11)).astype(float) + 0.5) / (1 << 53)

    def exponential(self, rows: np.ndarray) -> np.ndarray:
        return -np.log(self.uniform(rows))

    def normal(self, rows: np.ndarray) -> np.ndarray:
        return np.sqrt(2 * self.exponential(rows)) * np.cos(2 * np.pi * self.uniform(rows))


def pg_mean_of(b: np.ndarray) -> np.ndarray:
    small = np.abs(b) < 1e-6
    return np.where(small, 0.25, np.tanh(b / 2) / np.where(small, 1, 2 * b))


def pg_series(b: np.ndarray, rng: KeyedRandom, terms: int = 200) -> np.ndarray:
    """Draws from the truncated series of weighted exponentials, the tail replaced by its mean."""
    b = np.asarray(b, dtype=float)
    rows, out, seen = np.arange(len(b)), np.zeros(len(b)), np.zeros(len(b))
    for k in range(terms):
        weight = 1 / ((k + 0.5) ** 2 + b**2 / (4 * np.pi**2)) / (2 * np.pi**2)
        out += rng.exponential(rows) * weight
        seen += weight
    return out + pg_mean_of(b) - seen


def _inverse_gauss_below(z: np.ndarray, rng: KeyedRandom, rows: np.ndarray) -> np.ndarray:
    """Inverse Gaussian draws of mean 1 / z and shape 1, cut off above at _TRUNCATE."""
    out = np.empty(len(z))
    open_ = np.arange(len(z))
    while len(open_):
        zz, at = z[open_], rows[open_]
        wide = zz < 1 / _TRUNCATE
        x, ok = np.empty(len(open_)), np.zeros(len(open_), dtype=bool)
        if wide.any():
            e1, e2 = rng.exponential(at[wide]), rng.exponential(at[wide])
            x[wide] = _TRUNCATE / (1 + _TRUNCATE * e1) ** 2
            ok[wide] = (e1 * e1 <= 2 * e2 / _TRUNCATE) & (rng.uniform(at[wide]) <= np.exp(-0.5 * zz[wide] ** 2 * x[wide]))
        if (~wide).any():
            mu = 1 / zz[~wide]
            y = rng.normal(at[~wide]) ** 2
            v = mu + 0.5 * mu * mu * y - 0.5 * mu * np.sqrt(4 * mu * y + (mu * y) ** 2)
            x[~wide] = np.where(rng.uniform(at[~wide]) > mu / (mu + v), mu * mu / v, v)
            ok[~wide] = x[~wide] <= _TRUNCATE
        out[open_[ok]] = x[ok]
        open_ = open_[~ok]
    return out


def _coefficient(n: int, x: np.ndarray) -> np.ndarray:
    k = n + 0.5
    small = np.exp(-1.5 * np.log(np.pi * x / 2) + np.log(np.pi * k) - 2 * k * k / x)
    return np.where(x <= _TRUNCATE, small, np.pi * k * np.exp(-k * k * np.pi**2 * x / 2))


def _normal_cdf(x: np.ndarray) -> np.ndarray:
    return 0.5 * np.array([math.erfc(-v / math.sqrt(2)) for v in x])


def pg_exact(b: np.ndarray, rng: KeyedRandom) -> np.ndarray:
    """Exact draws: proposals from a tilted density in two parts, accepted by the partial sums of an alternating series."""
    z = np.abs(np.asarray(b, dtype=float)) / 2
    fz = np.pi**2 / 8 + z * z / 2
    root = math.sqrt(1 / _TRUNCATE)
    lower = np.exp(np.log(_normal_cdf(root * (_TRUNCATE * z - 1)) + 1e-300) - z) + np.exp(np.log(_normal_cdf(-root * (_TRUNCATE * z + 1)) + 1e-300) + z)
    p, q = np.pi / (2 * fz) * np.exp(-fz * _TRUNCATE), 2 * lower
    out = np.empty(len(z))
    open_ = np.arange(len(z))
    while len(open_):
        m = len(open_)
        tail = rng.uniform(open_) < p[open_] / (p[open_] + q[open_])
        x = np.empty(m)
        x[tail] = _TRUNCATE + rng.exponential(open_[tail]) / fz[open_[tail]]
        if (~tail).any():
            x[~tail] = _inverse_gauss_below(z[open_[~tail]], rng, open_[~tail])
        s = _coefficient(0, x)
        y = rng.uniform(open_) * s
        state = np.zeros(m, dtype=np.int8)
        for n in range(1, 60):
            live = state == 0
            if not live.any():
                break
            a = _coefficient(n, x)
            s = s - a if n % 2 else s + a
            state[live & ((y <= s) if n % 2 else (y > s))] = 1 if n % 2 else -1
        done = state == 1
        out[open_[done]] = x[done] / 4
        open_ = open_[~done]
    return out
