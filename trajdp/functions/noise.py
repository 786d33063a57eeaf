"""Noise as columns. Seeded noise is a function of (seed, stream, keys), alike in any engine that has MD5.

``draws(seed)`` gives the source of a mechanism's noise: with a seed the portable
one, which anyone who knows it can take off again (tests); without, the operating
system's, which can't be repeated (releases). ``Simulated`` is a fast generator for
experiments over many runs.
"""

from __future__ import annotations

import hashlib
import os
import zlib
from collections.abc import Iterator

import numpy as np
import pandas as pd
from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

from ..storage import kept

DIGITS, RANGE = 13, float(1 << 52)


def uniform(seed: int, stream: str, *keys: str | Column) -> Column:
    """A number in (0, 1) told by the first 52 bits of the MD5 of seed|stream|keys; keys are whole numbers."""
    parts = [F.lit(str(seed)), F.lit(stream), *[(F.col(k) if isinstance(k, str) else k).cast("string") for k in keys]]
    return (F.conv(F.substring(F.md5(F.concat_ws("|", *parts)), 1, DIGITS), 16, 10).cast("long") + F.lit(0.5)) / F.lit(RANGE)


def uniform_value(seed: int, stream: str, *keys: int) -> float:
    """The same number on the driver."""
    text = "|".join([str(seed), stream, *map(str, keys)])
    return (int(hashlib.md5(text.encode()).hexdigest()[:DIGITS], 16) + 0.5) / RANGE


def laplace(u: Column, scale: float | Column) -> Column:
    """Laplace noise of the scale from a uniform number."""
    return -F.lit(scale) * F.signum(u - 0.5) * F.log(1 - 2 * F.abs(u - 0.5)) if not isinstance(scale, Column) else -scale * F.signum(u - 0.5) * F.log(1 - 2 * F.abs(u - 0.5))


def laplace_value(u: float | np.ndarray, scale: float):
    return -scale * np.sign(u - 0.5) * np.log(1 - 2 * np.abs(u - 0.5))


def geometric(u: Column, v: Column, scale: float) -> Column:
    """Two-sided geometric noise: whole numbers with P(k) in proportion to exp(-|k| / scale)."""
    draw = lambda x: F.floor(F.log(x) * F.lit(-scale))
    return (draw(u) - draw(v)).cast("long")


def gumbel(u: Column) -> Column:
    return -F.log(-F.log(u))


def gumbel_value(u: float | np.ndarray):
    return -np.log(-np.log(u))


def secure(df: DataFrame, name: str = "u") -> DataFrame:
    """``df`` with a column of uniform numbers in (0, 1) from the operating system's randomness."""

    def draw(batches: Iterator[pd.DataFrame]) -> Iterator[pd.DataFrame]:
        for batch in batches:
            raw = np.frombuffer(os.urandom(8 * len(batch)), np.uint64) >> np.uint64(12)
            yield batch.assign(**{name: (raw + 0.5) / RANGE})

    kinds = ", ".join(f"`{c}` {t}" for c, t in df.dtypes)
    return df.mapInPandas(draw, f"{kinds}, {name} double")


class Seeded:
    """Portable noise: the same for a seed, stream and keys wherever it is drawn."""

    def __init__(self, seed: int):
        self.seed = seed

    def uniforms(self, stream: str, *keys: np.ndarray) -> np.ndarray:
        head, md5 = f"{self.seed}|{stream}|", hashlib.md5
        rows = zip(*(np.asarray(k).tolist() for k in keys))
        first = [int(md5((head + "|".join(map(str, row))).encode()).hexdigest()[:DIGITS], 16) for row in rows]
        return (np.array(first, float) + 0.5) / RANGE

    def drawn(self, df: DataFrame, name: str, stream: str, *keys: str) -> DataFrame:
        """``df`` with a column of uniform numbers."""
        return df.withColumn(name, uniform(self.seed, stream, *keys))


class Secure:
    """Noise from the operating system's randomness."""

    def uniforms(self, stream: str, *keys: np.ndarray) -> np.ndarray:
        raw = np.frombuffer(os.urandom(8 * len(keys[0])), np.uint64) >> np.uint64(12)
        return (raw + 0.5) / RANGE

    def drawn(self, df: DataFrame, name: str, stream: str, *keys: str) -> DataFrame:
        """``df`` with a column of uniform numbers, drawn once: a second draw would let the noise be averaged out."""
        return kept(secure(df, name))


class Simulated:
    """Noise of a fast generator, for experiments on the driver or in tasks."""

    def __init__(self, *seed: int):
        self.seed = seed

    def uniforms(self, stream: str, *keys: np.ndarray) -> np.ndarray:
        u = np.random.default_rng([*self.seed, zlib.crc32(stream.encode())]).random(len(keys[0]))
        return np.clip(u, 0.5 / RANGE, 1 - 0.5 / RANGE)


def draws(seed: int | None) -> Seeded | Secure:
    return Secure() if seed is None else Seeded(seed)
