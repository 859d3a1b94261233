"""Noise that depends on a key and the cell's coordinates only.

A task that runs again, or a plan that is dealt anew, then releases the same noise; fresh random
numbers would release a second draw for the same cell. The SQL form has 32-bit uniforms (the normal ends at about 6.7
standard deviations) and a public key: it is for tests and reproducible experiments. ``secret_normal`` takes
53-bit uniforms from a keyed digest of a secret. A key must never serve two true arrays with the same coordinates.
"""

from __future__ import annotations

import hashlib
import hmac
import math

import numpy as np
import pandas as pd
from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F
from pyspark.sql.functions import pandas_udf


def _uniform(digest: Column, start: int) -> Column:
    return (F.conv(F.substring(digest, start, 8), 16, 10).cast("double") + 0.5) / float(1 << 32)


def keyed_uniform(key: str, *columns: Column) -> Column:
    return _uniform(F.md5(F.concat_ws(":", F.lit(key), *[c.cast("string") for c in columns]).cast("binary")), 1)


def keyed_normal(key: str, *columns: Column) -> Column:
    """Standard normal from the key and the columns."""
    digest = F.md5(F.concat_ws(":", F.lit(key), *[c.cast("string") for c in columns]).cast("binary"))
    return F.sqrt(-2.0 * F.ln(_uniform(digest, 1))) * F.cos(2.0 * math.pi * _uniform(digest, 9))


def keyed_gumbel(key: str, *columns: Column) -> Column:
    return -F.ln(-F.ln(keyed_uniform(key, *columns)))


class PublicNoise:
    """Stands for a secret where a release must be reproducible in SQL: the noise of ``keyed_normal`` over key and cell. For public data only, as anyone can take it off."""

    @staticmethod
    def _uniform(text: str, start: int) -> float:
        return (int(hashlib.md5(text.encode()).hexdigest()[start : start + 8], 16) + 0.5) / (1 << 32)

    def normal(self, key: str, n: int) -> np.ndarray:
        texts = [f"{key}:{k}" for k in range(n)]
        return np.array([math.sqrt(-2.0 * math.log(self._uniform(t, 0))) * math.cos(2.0 * math.pi * self._uniform(t, 8)) for t in texts])

    def gumbel(self, key: str, n: int) -> np.ndarray:
        return np.array([-math.log(-math.log(self._uniform(f"{key}:{k}", 0))) for k in range(n)])


def secret_normal(secret: bytes | PublicNoise, key: str, n: int) -> np.ndarray:
    """n standard normals, the same for the same secret and key."""
    if isinstance(secret, PublicNoise):
        return secret.normal(key, n)
    seed = hmac.new(secret, key.encode(), hashlib.sha256).digest()
    return np.random.Generator(np.random.PCG64(int.from_bytes(seed, "big"))).standard_normal(n)


def secret_gumbel(secret: bytes | PublicNoise, key: str, n: int) -> np.ndarray:
    if isinstance(secret, PublicNoise):
        return secret.gumbel(key, n)
    seed = hmac.new(secret, key.encode(), hashlib.sha256).digest()
    return np.random.Generator(np.random.PCG64(int.from_bytes(seed, "big"))).gumbel(size=n)


def discrete_gaussian(secret: bytes, key: str, sigma: float, n: int) -> np.ndarray:
    """n integer Gaussians by rejection from a two-sided geometric, for counts that must stay whole."""
    seed = hmac.new(secret, key.encode(), hashlib.sha256).digest()
    rng = np.random.Generator(np.random.PCG64(int.from_bytes(seed, "big")))
    t = math.floor(sigma) + 1
    out = np.zeros(0, np.int64)
    while len(out) < n:
        size = 2 * (n - len(out)) + 16
        draw = rng.geometric(1 - math.exp(-1 / t), size) - 1
        sign = rng.integers(0, 2, size)
        signed = np.where(sign == 1, -draw, draw)
        ok = ~((sign == 1) & (draw == 0)) & (rng.random(size) < np.exp(-((draw - sigma * sigma / t) ** 2) / (2 * sigma * sigma)))
        out = np.concatenate([out, signed[ok]])
    return out[:n]


def add_secret_noise(cells: DataFrame, secret: bytes, key: str, sigma: float) -> DataFrame:
    """Noise of 53-bit uniforms on (gamma, cell, value), from the secret and each cell's coordinates."""

    @pandas_udf("double")
    def drawn(gamma: pd.Series, cell: pd.Series) -> pd.Series:
        def one(g: int, c: int) -> float:
            d = hmac.new(secret, f"{key}:{g}:{c}".encode(), hashlib.sha256).digest()
            u, v = ((int.from_bytes(d[k : k + 7], "big") >> 3) + 0.5 for k in (0, 7))
            return math.sqrt(-2 * math.log(u / 2**53)) * math.cos(2 * math.pi * v / 2**53)

        return pd.Series([one(g, c) for g, c in zip(gamma, cell)])

    return cells.withColumn("value", F.col("value") + sigma * drawn("gamma", "cell"))
