"""Randomness that is a function of (seed, id, stream): the same on any partitioning, engine and retry.

``hash01`` and what builds on it use MD5, which SQL engines share; ``gauss_block`` is the fast form for whole arrays.
"""

from __future__ import annotations

import math
from statistics import NormalDist

import numpy as np
from pyspark.sql import Column
from pyspark.sql import functions as F

SCALE = 2.0**52


def hash01(seed: int, *parts: Column | int) -> Column:
    """Uniform in [0, 1): the first 52 bits of the MD5 of ``seed|part|...``."""
    text = F.concat_ws("|", F.lit(str(seed)), *[(p if isinstance(p, Column) else F.lit(p)).cast("string") for p in parts])
    return F.conv(F.substring(F.md5(text), 1, 13), 16, 10).cast("long") / F.lit(SCALE)


def hash01_sql(seed: int, *parts: str) -> str:
    """The same in DuckDB's SQL."""
    text = " || '|' || ".join([f"'{seed}'", *[f"CAST({p} AS VARCHAR)" for p in parts]])
    return f"(CAST('0x' || substr(md5({text}), 1, 13) AS BIGINT) / {SCALE!r})"


def gauss(seed: int, node: Column, stream: Column | int) -> Column:
    """Standard normal, by the polar form of two uniforms; the first is taken from (0, 1]."""
    return F.sqrt(-2 * F.log(1 - hash01(seed, node, stream, 0))) * F.cos(2 * math.pi * hash01(seed, node, stream, 1))


def gauss_sql(seed: int, node: str, stream: str) -> str:
    return f"(sqrt(-2 * ln(1 - {hash01_sql(seed, node, stream, '0')})) * cos({2 * math.pi!r} * {hash01_sql(seed, node, stream, '1')}))"


def mixed(x: np.ndarray) -> np.ndarray:
    """A bijective scramble of unsigned 64-bit numbers."""
    x = (x ^ (x >> np.uint64(30))) * np.uint64(0xBF58476D1CE4E5B9)
    x = (x ^ (x >> np.uint64(27))) * np.uint64(0x94D049BB133111EB)
    return x ^ (x >> np.uint64(31))


def uniform_block(seed: int, ids: np.ndarray, width: int) -> np.ndarray:
    """A row of uniforms in (0, 1) for each id."""
    base = mixed(ids.astype("i8").view(np.uint64) + np.uint64((seed * 0x9E3779B97F4A7C15 + 1) % (1 << 64)))
    cells = mixed(base[:, None] + np.arange(1, width + 1, dtype=np.uint64) * np.uint64(0x9E3779B97F4A7C15))
    return ((cells >> np.uint64(12)).astype("f8") + 0.5) / SCALE


QUANTILES: list[np.ndarray] = []


def quantiles() -> np.ndarray:
    """The standard normal at 65,536 equally likely places."""
    if not QUANTILES:
        law = NormalDist()
        half = np.array([law.inv_cdf((k + 0.5) / 65536) for k in range(32768)], "f4")
        QUANTILES.append(np.concatenate([half, -half[::-1]]))
    return QUANTILES[0]


def gauss_block(seed: int, ids: np.ndarray, width: int) -> np.ndarray:
    """A row of ``width`` standard normals (float32) for each id; four of them come from each scrambled number."""
    base = mixed(ids.astype("i8").view(np.uint64) + np.uint64((seed * 0x9E3779B97F4A7C15 + 1) % (1 << 64)))
    words = -(-width // 4)
    cells = mixed(base[:, None] + np.arange(1, words + 1, dtype=np.uint64) * np.uint64(0x9E3779B97F4A7C15))
    return quantiles()[cells.view(np.uint16)][:, :width]
