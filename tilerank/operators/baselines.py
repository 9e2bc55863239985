"""In-memory and outside baselines."""

from __future__ import annotations

import os

import numpy as np
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from tilerank.functions import kernels as K
from tilerank.functions.keyed import DRAWS

from .matrix import Tall


def svd_dense(mat: Tall, vectors: bool = True) -> tuple:
    """U (as the small factor of the triangle), singular values, V: one pass to the triangle, then in memory."""
    r = mat.triangle()
    if not vectors:
        return None, np.linalg.svd(r, compute_uv=False), None
    u, d, vt = np.linalg.svd(r)
    return u, d, vt.T


def in_memory(mat: Tall, most: int = 1 << 30) -> np.ndarray:
    """The whole matrix on the driver, by row id, if it has at most ``most`` bytes: for the in-memory baselines."""
    size = 8 * mat.n * mat.df.count()
    if size > most:
        raise ValueError(f"{size} bytes are not for the driver's memory")
    rows = mat.df.orderBy("row_id").toArrow()["x"].combine_chunks()
    return rows.flatten().to_numpy(zero_copy_only=False).reshape(-1, mat.n)


def pivoted_qr_dense(a: np.ndarray) -> tuple[list[int], np.ndarray]:
    return K.pivoted(a)


def qr_dense(a: np.ndarray) -> np.ndarray:
    """Unpivoted; reveals no rank."""
    return K.positive(np.linalg.qr(a, mode="r"))


def utv_dense(a: np.ndarray, b: int, q: int, seed: int = 7, rng: str = "mix", threads: int | None = None) -> tuple[np.ndarray, np.ndarray, np.ndarray]:
    """The blocked UTV of an array, one kernel after the other, each with all BLAS threads (or ``threads`` of them)."""
    from .tiles import blas_threads

    width = -(-a.shape[1] // b) * b
    with blas_threads(threads or os.cpu_count() or 1):
        return K.utv(a, b, q, DRAWS[rng](seed, np.arange(len(a)), width))


def utv_tiles(a: np.ndarray, b: int, q: int, uv: bool = True, seed: int = 7, workers: int | None = None) -> tuple[np.ndarray, ...]:
    """U, T, V (T alone without ``uv``) by the tile ledger in memory: tasks beside each other, one BLAS thread each."""
    from tilerank.plans.ledger import plan_utv

    from .tiles import join_tiles, run_local, split

    m, n = a.shape
    rows, cols = -(-m // b), -(-n // b)
    tiles = split(a, b) | (split(np.eye(m), b, "U") | split(np.eye(n), b, "V") if uv else {})
    held = run_local(plan_utv(rows, cols, q, uv), tiles, m, n, b, seed, workers or os.cpu_count() or 1)
    t = join_tiles(held, "A", rows, cols)
    return (join_tiles(held, "U", rows, rows), t, join_tiles(held, "V", cols, cols)) if uv else (t,)


def gram_cholesky(mat: Tall) -> np.ndarray:
    """R from the Gram matrix: one light pass, the condition number squared."""
    return np.linalg.cholesky(mat.gram()).T


def gram_pivoted_cholesky(mat: Tall, k: int | None = None) -> tuple[list[int], np.ndarray]:
    """Order of the columns and k rows of R from the Gram matrix, the largest remaining diagonal first (ties to the smaller column)."""
    g = mat.gram()
    n = len(g)
    k = n if k is None else min(k, n)
    order, r = list(range(n)), np.zeros((k, n))
    for i in range(k):
        rest = np.diag(g)[order[i:]]
        if rest.max() <= 0:
            return order, r[:i]
        j = i + min(x for x in range(n - i) if rest[x] == rest.max())
        order.insert(i, order.pop(j))
        r[i] = g[order[i]] / np.sqrt(g[order[i], order[i]])
        r[i, order[:i]] = 0.0
        g = g - np.outer(r[i], r[i])
    return order, r[:, order]


def optimal_error(mat: Tall, k: int, values: np.ndarray | None = None) -> tuple[float, float]:
    """Spectral and Frobenius error of the best rank-k approximation; ``values``: the singular values, if known."""
    d = svd_dense(mat, False)[1] if values is None else values
    return (float(d[k]) if k < len(d) else 0.0), float(np.sqrt((d[k:] ** 2).sum()))


def spark_linalg(rows: DataFrame, k: int = 8) -> list[tuple]:
    """Spark's own row matrix: R of its tall-skinny QR, its singular values, and principal variances."""
    from pyspark.ml.feature import PCA
    from pyspark.ml.functions import array_to_vector
    from pyspark.mllib.linalg import Vectors
    from pyspark.mllib.linalg.distributed import RowMatrix

    m = RowMatrix(rows.rdd.map(lambda r: Vectors.dense(r.x)))
    r = m.tallSkinnyQR(False).R.toArray()
    out = [("tall_skinny_qr", i, float(abs(r[i, i]))) for i in range(k)]
    out += [("row_matrix_svd", i, float(v)) for i, v in enumerate(m.computeSVD(k).s)]
    model = PCA(k=k, inputCol="v", outputCol="p").fit(rows.select(array_to_vector(F.col("x")).alias("v")))
    return out + [("pca_variance", i, float(v)) for i, v in enumerate(model.explainedVariance)]
