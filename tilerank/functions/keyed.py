"""Standard normals keyed by (seed, row, column): the same in Spark, NumPy and SQL, and the same in a task's second run."""

from __future__ import annotations

import hashlib
import math

import numpy as np
from pyspark.sql import Column
from pyspark.sql import functions as F

SPAN = float(1 << 48)


def gaussian(seed: int, row: Column, col: Column) -> Column:
    """Box-Muller on two 48-bit slices of an MD5, in JVM functions."""
    h = F.md5(F.concat_ws("|", F.lit(str(seed)), row.cast("string"), col.cast("string")))
    u1 = (F.conv(F.substring(h, 1, 12), 16, 10).cast("long").cast("double") + 1.0) / (SPAN + 1.0)
    u2 = F.conv(F.substring(h, 13, 12), 16, 10).cast("long").cast("double") / SPAN
    return F.sqrt(-2.0 * F.log(u1)) * F.cos(2.0 * math.pi * u2)


def gaussian_sql(seed: int, row: str, col: str) -> str:
    """The same for DuckDB; ``row`` and ``col`` are SQL expressions."""
    h = f"md5(concat_ws('|', '{seed}', CAST({row} AS VARCHAR), CAST({col} AS VARCHAR)))"
    part = lambda a: f"CAST(CAST('0x' || substr({h}, {a}, 12) AS BIGINT) AS DOUBLE)"
    return f"sqrt(-2.0 * ln(({part(1)} + 1.0) / 281474976710657.0)) * cos(2.0 * pi() * ({part(13)} / 281474976710656.0))"


def gaussians(seed: int, rows, cols: int, first: int = 0) -> np.ndarray:
    """len(rows) x cols, NumPy twin of ``gaussian``."""
    out = np.empty((len(rows), cols))
    for i, r in enumerate(rows):
        for j in range(cols):
            h = hashlib.md5(f"{seed}|{r}|{first + j}".encode()).hexdigest()
            u1, u2 = (int(h[:12], 16) + 1.0) / (SPAN + 1.0), int(h[12:24], 16) / SPAN
            out[i, j] = math.sqrt(-2.0 * math.log(u1)) * math.cos(2.0 * math.pi * u2)
    return out


def mixed(seed: int, rows: np.ndarray, cols: int, first: int = 0) -> np.ndarray:
    """A fast keyed draw for benchmarks: integer mixing of (seed, row, column) in whole arrays."""

    def mix(x: np.ndarray) -> np.ndarray:
        x = (x ^ (x >> np.uint64(30))) * np.uint64(0xBF58476D1CE4E5B9)
        x = (x ^ (x >> np.uint64(27))) * np.uint64(0x94D049BB133111EB)
        return x ^ (x >> np.uint64(31))

    with np.errstate(over="ignore"):
        key = mix(np.asarray(rows).astype(np.uint64)[:, None] * np.uint64(0x9E3779B97F4A7C15) + np.uint64(seed))
        key = mix(key + np.arange(first, first + cols, dtype=np.uint64)[None, :] * np.uint64(0xD1B54A32D192ED03))
        u1 = ((key >> np.uint64(11)).astype(float) + 1.0) / (float(1 << 53) + 1.0)
        u2 = (mix(key + np.uint64(1)) >> np.uint64(11)).astype(float) / float(1 << 53)
    return np.sqrt(-2.0 * np.log(u1)) * np.cos(2.0 * np.pi * u2)


DRAWS = {"md5": gaussians, "mix": mixed}
