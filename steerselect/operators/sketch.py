"""Signed hash sketches: each coordinate goes to one bucket with one sign; dot products stay unbiased."""

from __future__ import annotations

import numpy as np
from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

#: The modulus of the arithmetic hash; products of 31-bit numbers stay within a long.
PRIME = (1 << 31) - 1


def multipliers(seed: int = 42, layer: int = 0) -> tuple[int, int, int, int]:
    r = np.random.default_rng([seed, layer])
    return tuple(int(v) for v in r.integers(1, PRIME, 4))


def sql_bucket(coordinate: str, buckets: int, seed: int = 42, layer: int = 0) -> tuple[str, str]:
    """Bucket and sign of an integer coordinate, as expressions that Spark and other SQL engines read alike."""
    a, b, c, d = multipliers(seed, layer)
    return f"((({a} * ({coordinate}) + {b}) % {PRIME}) % {buckets})", f"(1 - 2 * ((({c} * ({coordinate}) + {d}) % {PRIME}) % 2))"


def sketch_rows(coords: DataFrame, keys: list[str], coordinate: str, value: Column, buckets: int, seed: int = 42, layer: int = 0) -> DataFrame:
    """(keys..., bucket, val) of sparse coordinates; sums are combined before the shuffle."""
    h, s = (F.expr(e) for e in sql_bucket(coordinate, buckets, seed, layer))
    return coords.select(*keys, h.alias("bucket"), (s * value).alias("v")).groupBy(*keys, "bucket").agg(F.sum("v").alias("val"))


def tables(shape: tuple[int, int], buckets: int, seed: int = 42, layer: int = 0) -> tuple[np.ndarray, np.ndarray]:
    """(bucket, sign) per coordinate of a matrix, row by row: the arithmetic hash, cached by callers per shape."""
    a, b, c, d = multipliers(seed, layer)
    i = np.arange(shape[0] * shape[1], dtype=object)
    h = np.array((a * i + b) % PRIME % buckets, np.int64)
    s = np.array(1 - 2 * ((c * i + d) % PRIME % 2), np.float64)
    return h.reshape(shape), s.reshape(shape)


def sketch(g: np.ndarray, table: tuple[np.ndarray, np.ndarray], buckets: int) -> np.ndarray:
    h, s = table
    return np.bincount(h.ravel(), (s * g).ravel(), buckets)


def factored_tables(shape: tuple[int, int], buckets: int, seed: int = 42, layer: int = 0) -> tuple[np.ndarray, ...]:
    """h(i, j) = h1(i) + h2(j) mod buckets and s(i, j) = s1(i) s2(j), as (h1, s1, h2, s2)."""
    r = np.random.default_rng([seed, layer, 1])
    return (r.integers(0, buckets, shape[0]), r.choice([-1.0, 1.0], shape[0]), r.integers(0, buckets, shape[1]), r.choice([-1.0, 1.0], shape[1]))


def sketch_outer(b: np.ndarray, a: np.ndarray, table: tuple[np.ndarray, ...], buckets: int) -> np.ndarray:
    """Sketch of the sum over positions of outer products b_t a_t, never formed: a circular convolution of two sketches."""
    h1, s1, h2, s2 = table
    n = len(b)
    rows = np.zeros((n, buckets))
    cols = np.zeros((n, buckets))
    np.add.at(rows, (slice(None), h1), b * s1)
    np.add.at(cols, (slice(None), h2), a * s2)
    return np.fft.irfft((np.fft.rfft(rows) * np.fft.rfft(cols)).sum(0), buckets)
