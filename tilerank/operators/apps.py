"""What rank-revealing factorizations are for: least squares, total least squares, subset selection, approximation."""

from __future__ import annotations

import hashlib
from collections import Counter
from collections.abc import Iterator

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from tilerank.functions import kernels as K

from . import utv
from .matrix import Tall, write_step


def lstsq(mat: Tall, n: int, tol: float = 1e-10) -> tuple[np.ndarray, float]:
    """Columns 0..n-1 against column n, from one pass: the pivoted triangle is cut at its numerical rank, dropped columns get zero."""
    r = mat.triangle(list(range(n + 1)))
    order, t = K.pivoted(r[:, :n])
    d = np.abs(np.diag(t))
    rank = int((d > tol * d.max()).sum())
    chosen = order[:rank]
    q, u = np.linalg.qr(r[:, chosen])
    x = np.zeros(n)
    x[chosen] = K.solve_upper(u, (q.T @ r[:, n])[:, None])[:, 0]
    return x, float(np.linalg.norm(r[:, n] - r[:, :n] @ x))


def tls(mat: Tall, n: int) -> np.ndarray:
    """Total least squares of columns 0..n-1 against column n, errors in all of them."""
    v = np.linalg.svd(mat.triangle(list(range(n + 1))))[2][-1]
    if abs(v[n]) < 1e-14:
        raise ValueError("no total least squares solution")
    return -v[:n] / v[n]


def select_columns(mat: Tall, k: int) -> list[int]:
    from .sketchqr import pivoted_qr

    return pivoted_qr(mat, k).perm[:k]


def term_rows(docs: DataFrame, buckets: int) -> DataFrame:
    """Documents as hashed word counts, log-scaled: a row frame. Words are counted where their text is; rows of one id count together."""

    def count(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        known: dict[str, int] = {}
        for batch in batches:
            places, times = [], []
            for words in batch.column(1).to_pylist():
                seen: Counter[int] = Counter()
                for w, n in Counter(words).items():
                    if w not in known:
                        if len(known) > 200_000:
                            known.clear()
                        known[w] = int.from_bytes(hashlib.md5(w.encode()).digest()[:4], "big") % buckets
                    seen[known[w]] += n
                places.append(list(seen))
                times.append(list(seen.values()))
            yield pa.RecordBatch.from_arrays([batch.column(0), pa.array(places, pa.list_(pa.int32())), pa.array(times, pa.list_(pa.int64()))], names=["row_id", "c", "n"])

    def dense(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in batches:
            a = np.zeros((batch.num_rows, buckets))
            row = np.repeat(np.arange(batch.num_rows), batch.column(1).value_lengths().to_numpy())
            np.add.at(a, (row, batch.column(1).flatten().to_numpy()), batch.column(2).flatten().to_numpy())
            x = pa.ListArray.from_arrays(pa.array(np.arange(0, a.size + 1, buckets), pa.int32()), pa.array(np.log1p(a).ravel()))
            yield pa.RecordBatch.from_arrays([batch.column(0), x], names=["row_id", "x"])

    kind = docs.schema["doc_id"].dataType.simpleString()
    split = docs.select(F.col("doc_id").alias("row_id"), F.split(F.lower(F.coalesce("text", F.lit(""))), "\\s+").alias("w"))
    counts = split.mapInArrow(count, f"row_id {kind}, c array<int>, n array<long>")
    merged = counts.groupBy("row_id").agg(F.collect_list(F.struct("c", "n")).alias("p")).select("row_id", F.flatten("p.c").alias("c"), F.flatten("p.n").alias("n"))
    return merged.mapInArrow(dense, f"row_id {kind}, x array<double>")


def kept_energy(mat: Tall, ks: list[int], seed: int) -> list[tuple]:
    """Share of the squared norm that rank-k approximations keep."""
    f = utv.power_utv(mat, max(ks), 1, max(ks), "triangle", seed, rng="mix")
    r = mat.triangle()
    total = float((r**2).sum())
    return [(k, float((np.linalg.qr(r @ f.v[:, :k])[0].T @ r).__pow__(2).sum() / total)) for k in ks]


def term_classes(rows: DataFrame, digits: int = 9) -> DataFrame:
    """(row_id, first_id): each row with the smallest id of the rows equal to it (to so many digits)."""

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in batches:
            keys = [hashlib.md5((np.round(x.values.to_numpy(zero_copy_only=False), digits) + 0.0).tobytes()).digest() for x in batch.column(1)]
            yield pa.RecordBatch.from_arrays([batch.column(0), pa.array(keys, pa.binary())], names=["row_id", "key"])

    key = rows.select("row_id", "x").mapInArrow(run, f"row_id {rows.schema['row_id'].dataType.simpleString()}, key binary")
    first = key.groupBy("key").agg(F.min("row_id").alias("first_id"))
    return key.join(first, "key").select("row_id", "first_id")


#: Rows of a slab, the unit in which near pairs are looked for.
SLAB = 4096
#: What single precision may take from a product of rows of norm one.
SINGLE = 1e-4


def slabs_of(points: DataFrame, width: int, cells: int) -> DataFrame:
    """``row_id``, ``cell``, ``x`` (floats: ``width`` coordinates, then the row) -> slabs of up to SLAB rows of one cell: ``slab`` (its
    first id), ``cell``, ``lo`` and ``hi`` (the coordinates' bounds), ``ids``, ``x`` (the rows as floats)."""

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        ids, rows, at = [], [], None

        def full() -> pa.RecordBatch:
            a = np.array(rows, np.float32)
            y, x = a[:, :width], np.ascontiguousarray(a[:, width:])
            got = [[ids[0]], [list(at)], [y.min(0).tolist()], [y.max(0).tolist()], [np.array(ids, np.int64).tobytes()], [x.tobytes()]]
            return pa.RecordBatch.from_arrays([pa.array(v, t) for v, t in zip(got, types, strict=True)], names=["slab", "cell", "lo", "hi", "ids", "x"])

        types = [pa.int64(), pa.list_(pa.int64()), pa.list_(pa.float64()), pa.list_(pa.float64()), pa.binary(), pa.binary()]
        for batch in batches:
            a = batch.column("x").flatten().to_numpy(zero_copy_only=False).reshape(batch.num_rows, -1)
            for i, cell, row in zip(batch.column("row_id").to_pylist(), map(tuple, batch.column("cell").to_pylist()), a, strict=True):
                if ids and (cell != at or len(ids) == SLAB):
                    yield full()
                    ids, rows = [], []
                at = cell
                ids.append(i)
                rows.append(row)
        if ids:
            yield full()

    ordered = points.select("row_id", "cell", "x").repartitionByRange("cell", "row_id").sortWithinPartitions("cell", "row_id")
    return ordered.mapInArrow(run, "slab long, cell array<long>, lo array<double>, hi array<double>, ids binary, x binary")


def near_pairs(rows: DataFrame, n: int, cosine: float, width: int = 12, cells: int = 3) -> DataFrame:
    """(a, b, cosine) for all pairs of different rows, one for each class of equal ones, whose cosine is at least ``cosine``.

    Rows of norm one that are so alike lie within a distance of sqrt(2 - 2 cosine), and so do their projections on any orthonormal
    columns. The leading right basis of a UTV factorization of the centred rows spreads them most: its first ``cells`` coordinates
    are cut into cells of that width, whose rows make slabs. A slab meets those of its own and the adjoining cells whose bounds in ``width``
    coordinates are near enough, by a matrix product in single precision; the rows' own product decides on the pairs that it
    leaves. No pair is lost. Slabs are read where they meet and never shuffled; the products fall with ``cells``.
    """
    rows = write_step(rows, "terms")
    kept = rows.join(term_classes(rows).where("row_id = first_id").select("row_id"), "row_id", "left_semi")

    def scale(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in batches:
            a = np.array(batch.column(1).flatten().to_numpy(zero_copy_only=False)).reshape(-1, n)
            size = np.sqrt((a * a).sum(1))
            a = a[size > 0] / size[size > 0, None]
            x = pa.ListArray.from_arrays(pa.array(np.arange(0, a.size + 1, n), pa.int32()), pa.array(a.ravel()))
            yield pa.RecordBatch.from_arrays([batch.column(0).filter(pa.array(size > 0)), x], names=["row_id", "x"])

    unit = write_step(kept.select("row_id", "x").mapInArrow(scale, f"row_id {rows.schema['row_id'].dataType.simpleString()}, x array<double>"), "unit")
    if unit.isEmpty():
        return unit.select(F.col("row_id").alias("a"), F.col("row_id").alias("b"), F.lit(0.0).alias("cosine"))
    mat = Tall(unit, n)
    mean = mat.reduce(lambda _, a: np.vstack([a.sum(0), np.full(a.shape[1], len(a))]))
    mean = mean[0] / mean[1]
    centred = Tall(mat.map_rows(lambda _, a: a - mean), n)
    v = utv.power_utv(centred, width, 1, width, "triangle", rng="mix").v[:, :width]
    width, cells = v.shape[1], min(cells, v.shape[1])
    # a little further than the bound, as coordinates are rounded
    far = float(np.sqrt(max(2 - 2 * cosine, 0.0))) * (1 + 1e-5) + 1e-5
    points = mat.map_rows(lambda _, a: np.hstack([(a - mean) @ v, a])).withColumn("x", F.col("x").cast("array<float>"))
    points = points.withColumn("cell", F.array(*[F.floor(F.get("x", F.lit(c)).cast("double") / far) for c in range(cells)]))
    slabs = write_step(slabs_of(points, width, cells), "slabs")
    s, t = (slabs.select([F.col(c).alias(f"{side}_{c}") for c in slabs.columns]) for side in "st")
    apart = F.lit(0.0)
    for c in range(width):
        gap = F.greatest(F.lit(0.0), F.get("t_lo", F.lit(c)) - F.get("s_hi", F.lit(c)), F.get("s_lo", F.lit(c)) - F.get("t_hi", F.lit(c)))
        apart = apart + gap * gap
    beside = F.col("s_slab") <= F.col("t_slab")
    for c in range(cells):
        beside = beside & (F.abs(F.get("s_cell", F.lit(c)) - F.get("t_cell", F.lit(c))) <= 1)
    met = s.join(t.hint("shuffle_replicate_nl"), beside & (apart <= far * far)).select("s_ids", "s_x", "t_ids", "t_x")

    def alike(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in batches:
            for k in range(batch.num_rows):
                i, p, j, q = (np.frombuffer(batch.column(c)[k].as_buffer(), t) for c, t in enumerate((np.int64, np.float32) * 2))
                p, q, same = p.reshape(-1, n), q.reshape(-1, n), i[0] == j[0]
                for lo in range(0, len(i), 1024):
                    u, w = np.nonzero(p[lo : lo + 1024] @ q.T >= cosine - SINGLE)
                    x, y = i[lo + u], j[w]
                    keep = x < y if same else slice(None)
                    x, y = x[keep], y[keep]
                    if len(x):
                        yield pa.RecordBatch.from_arrays([pa.array(np.minimum(x, y)), pa.array(np.maximum(x, y))], names=["a", "b"])

    found = write_step(met.mapInArrow(alike, "a long, b long"), "met")
    both = found.join(unit.toDF("a", "x"), "a").join(unit.toDF("b", "w"), "b")
    product = F.aggregate(F.zip_with("x", "w", lambda a, b: a * b), F.lit(0.0), lambda s, d: s + d)
    return both.select("a", "b", product.alias("cosine")).where(F.col("cosine") >= cosine)
