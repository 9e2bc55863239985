"""Running a ledger on real tiles: in memory, or as Spark jobs wave by wave.

A tile store is a frame ``name``, ``nr``, ``nc``, ``data``. Tiles are never changed: a wave writes those that it makes as a version of
their own, ``version=w/panel=...`` with a panel for each tile column of each matrix, and a manifest on the driver (a
number for each tile) says which version of a tile is the last. A wave reads just the (version, panel) folders that its tasks' blocks are in,
and brings the blocks to the tasks by a join on name and version, one group a task (at most four tiles). What a run writes is thus what its tasks
change. A version with its success mark is finished, so a run that is started again on the same folder goes on where it stopped.

``direct`` reads a wave's blocks when the wave runs. ``overlap`` has a second lane: while a wave runs, another thread reads the blocks that the next wave
needs and that are there already into the block manager. Both keep a trace of each lane's start and end.
"""

from __future__ import annotations

import time
import uuid
from concurrent.futures import ThreadPoolExecutor
from contextlib import contextmanager
from dataclasses import dataclass, field

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from tilerank.functions import kernels as K
from tilerank.functions.keyed import DRAWS
from tilerank.plans.ledger import Task, waves

from .matrix import shared_root

TILE = "bi int, bj int, nr int, nc int, data binary"
STORE = "name string, nr int, nc int, data binary"


def unit_lower(y: np.ndarray) -> np.ndarray:
    k = min(y.shape)
    w = np.tril(y[:, :k], -1)
    w[np.arange(k), np.arange(k)] = 1.0
    return w


def stacked_w(low: np.ndarray) -> np.ndarray:
    """The reflectors of a triangle on a dense tile: identity on top."""
    return np.vstack([np.eye(low.shape[1]), low])


def run_task(op: str, args: tuple, ins: list[np.ndarray], shapes: dict, seed: int, b: int) -> list[np.ndarray]:
    """Out-blocks of one task."""
    if op == "draw":
        step, r = args
        rows = np.arange(shapes["rows"][r]) + r * b
        return [DRAWS["mix"](seed + 1000 * step, rows, shapes["cols"][step])]
    if op in ("gemm_tn_set", "gemm_tn_add"):
        return [ins[0].T @ ins[1] + (ins[2] if op.endswith("add") else 0.0)]
    if op in ("gemm_nn_set", "gemm_nn_add"):
        return [ins[0] @ ins[1] + (ins[2] if op.endswith("add") else 0.0)]
    if op == "qr_dense":
        r, w, s = K.reflectors(ins[0])
        out = np.triu(r)
        k = w.shape[1]
        out[:, :k] += np.tril(w, -1)
        return [out, s]
    if op == "qr_stacked":
        top, low = ins
        n = top.shape[1]
        h = min(len(top), n)
        tri = np.zeros((n, n))
        tri[:h] = np.triu(top[:h])
        r, w, s = K.reflectors(np.vstack([tri, low]))
        new = top.copy()
        new[:h] = np.tril(top[:h], -1) + np.triu(r[:h])
        return [new, w[n:], s]
    if op == "qr_tree":
        upper, lower = ins
        n = upper.shape[1]
        h, g = min(len(upper), n), min(len(lower), n)
        tri, low = np.zeros((n, n)), np.zeros((n, n))
        tri[:h], low[:g] = np.triu(upper[:h]), np.triu(lower[:g])
        r, w, s = K.reflectors(np.vstack([tri, low]))
        new = upper.copy()
        new[:h] = np.tril(upper[:h], -1) + np.triu(r[:h])
        return [new, w[n:], s]
    if op == "left_tree":
        low, s, top, x = ins
        n = low.shape[1]
        a, c = np.zeros((n, top.shape[1])), np.zeros((n, top.shape[1]))
        a[: min(len(top), n)], c[: min(len(x), n)] = top[:n], x[:n]
        both = K.apply_left(stacked_w(low), s, np.vstack([a, c]))
        return [np.vstack([both[:n][: len(top)], top[n:]]), np.vstack([both[n:][: len(x)], x[n:]])]
    if op == "left_dense":
        return [K.apply_left(unit_lower(ins[0]), ins[1], ins[2])]
    if op == "right_dense":
        return [K.apply_right(unit_lower(ins[0]), ins[1], ins[2])]
    if op == "left_stacked":
        low, s, top, x = ins
        n = low.shape[1]
        both = K.apply_left(stacked_w(low), s, np.vstack([top[:n], x]))
        return [np.vstack([both[:n], top[n:]]), both[n:]]
    if op == "right_stacked":
        low, s, left, x = ins
        n = low.shape[1]
        both = K.apply_right(stacked_w(low), s, np.hstack([left[:, :n], x]))
        return [np.hstack([both[:, :n], left[:, n:]]), both[:, n:]]
    if op == "keep_upper":
        return [np.triu(ins[0])]
    if op == "set_zero":
        return []
    if op == "svd":
        a = ins[0]
        h = min(a.shape)
        # a tall tile that no triangle was made of (the last one of a grid with more rows than columns) takes all its rows
        u, d, v = K.small_svd(a[:h] if not a[h:].any() else a)
        out = np.zeros_like(a)
        out[np.arange(h), np.arange(h)] = d
        return [out, u, v]
    if op == "times_left":
        u, x = ins
        h = len(u)
        return [np.vstack([u.T @ x[:h], x[h:]])]
    if op == "times_right":
        x, v = ins
        h = len(v)
        return [np.hstack([x[:, :h] @ v, x[:, h:]])]
    raise ValueError(op)


def grid_shapes(m: int, n: int, b: int) -> dict:
    return {"rows": [min(b, m - i) for i in range(0, m, b)], "cols": [min(b, n - j) for j in range(0, n, b)]}


def zero_of(name: str, shapes: dict) -> np.ndarray:
    _, i, j = name.split("_")
    return np.zeros((shapes["rows"][int(i)], shapes["cols"][int(j)]))


def split(a: np.ndarray, b: int, name: str = "A") -> dict[str, np.ndarray]:
    return {f"{name}_{i // b}_{j // b}": a[i : i + b, j : j + b].copy() for i in range(0, a.shape[0], b) for j in range(0, a.shape[1], b)}


def join_tiles(tiles: dict[str, np.ndarray], name: str, rows: int, cols: int) -> np.ndarray:
    return np.block([[tiles[f"{name}_{i}_{j}"] for j in range(cols)] for i in range(rows)])


@contextmanager
def blas_threads(n: int):
    """Let BLAS use ``n`` threads inside; -> whether this NumPy's library could be told."""
    calls = blas_calls()
    if calls is None:
        yield False
        return
    get, put = calls
    before = get()
    put(n)
    try:
        yield True
    finally:
        put(before)


def blas_calls():
    """(get, set) for the number of threads of the OpenBLAS that comes with NumPy, or None."""
    import ctypes
    from pathlib import Path

    for lib in Path(np.__file__).parent.parent.glob("numpy.libs/*openblas*"):
        handle = ctypes.CDLL(str(lib))
        for prefix, suffix in (("scipy_openblas", "64_"), ("openblas", "64_"), ("openblas", "")):
            get, put = (getattr(handle, f"{prefix}_{x}_num_threads{suffix}", None) for x in ("get", "set"))
            if get and put:
                return get, put
    return None


def run_local(tasks: list[Task], tiles: dict[str, np.ndarray], m: int, n: int, b: int, seed: int = 7, workers: int = 1) -> dict[str, np.ndarray]:
    """All tiles in memory. With several workers the tasks of a wave run beside each other, each with one BLAS thread."""
    shapes, held = grid_shapes(m, n, b), dict(tiles)

    def one(t: Task) -> list[np.ndarray]:
        return [zero_of(t.outs[0], shapes)] if t.op == "set_zero" else run_task(t.op, t.args, [held[x] for x in t.ins], shapes, seed, b)

    if workers == 1:
        for t in tasks:
            held.update(zip(t.outs, one(t), strict=True))
        return held
    by_wave: dict[int, list[Task]] = {}
    for t, w in zip(tasks, waves(tasks), strict=True):
        by_wave.setdefault(w, []).append(t)
    with blas_threads(1), ThreadPoolExecutor(workers) as pool:
        for w in sorted(by_wave):
            for t, got in zip(by_wave[w], list(pool.map(one, by_wave[w])), strict=True):
                held.update(zip(t.outs, got, strict=True))
    return held


def store(tiles: DataFrame, name: str = "A") -> DataFrame:
    """Tile frame -> tile store."""
    return tiles.select(F.format_string(f"{name}_%d_%d", "bi", "bj").alias("name"), "nr", "nc", "data")


def grid(tiles: DataFrame, name: str) -> DataFrame:
    """One matrix of a tile store -> tile frame."""
    own = tiles.where(F.split("name", "_")[0] == name)
    return own.select(F.split("name", "_")[1].cast("int").alias("bi"), F.split("name", "_")[2].cast("int").alias("bj"), "nr", "nc", "data")


def multiply(x: DataFrame, y: DataFrame) -> DataFrame:
    """X Y of tile frames: joined on the contraction index, products summed within batches and then by place. Missing tiles are zero."""
    pairs = x.select("bi", F.col("bj").alias("k"), "nr", F.col("nc").alias("w"), F.col("data").alias("x")).join(y.select(F.col("bi").alias("k"), "bj", "nc", F.col("data").alias("y")), "k")

    def products(batches):
        for p in batches:
            sums: dict[tuple[int, int], np.ndarray] = {}
            for r in p.to_pylist():
                made = np.frombuffer(r["x"]).reshape(r["nr"], r["w"]) @ np.frombuffer(r["y"]).reshape(r["w"], r["nc"])
                at = (r["bi"], r["bj"])
                sums[at] = sums[at] + made if at in sums else made
            yield tile_batch(sums)

    def total(key: tuple[pa.Scalar, ...], t: pa.Table) -> pa.Table:
        parts = [np.frombuffer(r["data"]).reshape(r["nr"], r["nc"]) for r in t.to_pylist()]
        return pa.Table.from_batches([tile_batch({(key[0].as_py(), key[1].as_py()): sum(parts[1:], parts[0])})])

    return pairs.select("bi", "bj", "nr", "nc", "w", "x", "y").mapInArrow(products, TILE).groupBy("bi", "bj").applyInArrow(total, TILE)


def multiply_thin(x: DataFrame, y: DataFrame, rows: int, cols: int, side: int = 128) -> DataFrame:
    """X Y of tile frames with a short contraction index, for a result of ``rows`` x ``cols`` tiles: cut into squares of ``side`` tiles, each made
    whole in one task. X is sent once for each column of squares and Y for each row of them; no product is shuffled."""
    down, across = -(-rows // side) - 1, -(-cols // side) - 1
    left = x.withColumn("gi", F.floor(F.col("bi") / side).cast("int")).withColumn("gj", F.explode(F.sequence(F.lit(0), F.lit(max(across, 0)))))
    right = y.withColumn("gj", F.floor(F.col("bj") / side).cast("int")).withColumn("gi", F.explode(F.sequence(F.lit(0), F.lit(max(down, 0)))))

    def square(p: pa.Table, q: pa.Table) -> pa.Table:
        by_k: dict[int, list[dict]] = {}
        for r in q.to_pylist():
            by_k.setdefault(r["bi"], []).append(r)
        beside = {k: ([r["bj"] for r in t], np.cumsum([0, *(r["nc"] for r in t)]), np.hstack([np.frombuffer(r["data"]).reshape(r["nr"], r["nc"]) for r in t])) for k, t in by_k.items()}
        sums: dict[tuple[int, int], np.ndarray] = {}
        for r in p.to_pylist():
            if r["bj"] in beside:
                places, ends, wide = beside[r["bj"]]
                made = np.frombuffer(r["data"]).reshape(r["nr"], r["nc"]) @ wide
                for n, j in enumerate(places):
                    part, at = made[:, ends[n] : ends[n + 1]], (r["bi"], j)
                    sums[at] = sums[at] + part if at in sums else part
        return pa.Table.from_batches([tile_batch(sums)])

    return left.groupBy("gi", "gj").cogroup(right.groupBy("gi", "gj")).applyInArrow(square, TILE)


def combine(x: DataFrame, y: DataFrame, f) -> DataFrame:
    """``f(tile of x, tile of y)`` place by place: sums, differences, a x + y, entrywise products. A tile that only one side has meets zeros."""

    def run(batches):
        for p in batches:
            out = {}
            for r in p.to_pylist():
                zero = np.zeros((r["nr"], r["nc"]))
                a, b = (zero if r[c] is None else np.frombuffer(r[c]).reshape(zero.shape) for c in ("x", "y"))
                out[r["bi"], r["bj"]] = np.ascontiguousarray(f(a, b), dtype=float)
            yield tile_batch(out)

    both = x.withColumnRenamed("data", "x").join(y.withColumnRenamed("data", "y"), ["bi", "bj", "nr", "nc"], "full")
    return both.select("bi", "bj", "nr", "nc", "x", "y").mapInArrow(run, TILE)


def trailing(tiles: DataFrame, i: int) -> DataFrame:
    """The tiles from row and column i on; the filter reaches the scan."""
    return tiles.where((F.col("bi") >= i) & (F.col("bj") >= i))


def tile_batch(tiles: dict[tuple[int, int], np.ndarray]) -> pa.RecordBatch:
    places, data = list(tiles), [np.ascontiguousarray(a) for a in tiles.values()]
    ints = [pa.array(c, pa.int32()) for c in ([p[0] for p in places], [p[1] for p in places], [a.shape[0] for a in data], [a.shape[1] for a in data])]
    return pa.RecordBatch.from_arrays([*ints, pa.array([a.tobytes() for a in data], pa.binary())], names=["bi", "bj", "nr", "nc", "data"])


def panel_of(name: str) -> str:
    """The folder of a tile: its matrix and its tile column."""
    kind, _, place = name.partition("_")
    return f"{kind}_{place.rpartition('_')[2]}"


@dataclass
class TileRun:
    """The versions of all tiles, what was read and written (tiles and bytes, without the first version), and the lanes' times."""

    spark: SparkSession
    root: str
    manifest: dict[str, int]
    read: list[int] = field(default_factory=lambda: [0, 0])
    written: list[int] = field(default_factory=lambda: [0, 0])
    trace: list[tuple[str, int, float, float, int]] = field(default_factory=list)

    def folders(self, names) -> list[str]:
        return sorted({f"{self.root}/version={self.manifest[x]}/panel={panel_of(x)}" for x in names})

    def tiles(self, kind: str | None = None) -> DataFrame:
        """The last version of all tiles, or of one matrix's."""
        names = [x for x in self.manifest if kind is None or x.partition("_")[0] == kind]
        if not names:
            return self.spark.createDataFrame([], STORE)
        wanted = self.spark.createDataFrame([(x, self.manifest[x]) for x in names], "name string, made int")
        found = self.spark.read.schema(f"{STORE}, made int").parquet(*self.folders(names))
        return found.join(wanted, ["name", "made"], "left_semi").drop("made")


def worker(arguments: dict[int, tuple], shapes: dict, seed: int, b: int):
    """What a group does: one task on its blocks."""

    def work(key: tuple[pa.Scalar, ...], t: pa.Table) -> pa.Table:
        op, args, ins, outs = arguments[key[0].as_py()]
        held = {x["name"]: np.frombuffer(x["data"]).reshape(x["nr"], x["nc"]) for x in t.to_pylist() if x["data"] is not None}
        got = [zero_of(outs[0], shapes)] if op == "set_zero" else run_task(op, args, [held[x] if x in held else zero_of(x, shapes) for x in ins], shapes, seed, b)
        return pa.table({"name": outs, "nr": pa.array([g.shape[0] for g in got], pa.int32()), "nc": pa.array([g.shape[1] for g in got], pa.int32()), "data": pa.array([np.ascontiguousarray(g).tobytes() for g in got], pa.binary())})

    return work


def run_waves(tasks: list[Task], tiles: DataFrame, m: int, n: int, b: int, seed: int = 7, mode: str = "overlap", root: str | None = None) -> TileRun:
    """The same on executors: a job for each wave; missing tiles are zero."""
    if mode not in ("direct", "overlap"):
        raise ValueError(f"no mode {mode}")
    spark, shapes = tiles.sparkSession, grid_shapes(m, n, b)
    root = root or f"{shared_root(spark)}/tiles-{uuid.uuid4().hex}"
    run = TileRun(spark, root, {})
    began = time.time()

    def put(df: DataFrame, version: int) -> None:
        place = F.regexp_replace("name", "_(?:[0-9]+_)?([0-9]+)$", "_$1")
        df.withColumns({"made": F.lit(version), "panel": place}).write.mode("overwrite").partitionBy("panel").parquet(f"{root}/version={version}")

    def done(version: int) -> bool:
        path = spark.sparkContext._jvm.org.apache.hadoop.fs.Path(f"{root}/version={version}/_SUCCESS")
        return path.getFileSystem(spark.sparkContext._jsc.hadoopConfiguration()).exists(path)

    def names_of(version: int) -> list[str]:
        return [r["name"] for r in spark.read.parquet(f"{root}/version={version}").select("name").collect()]

    if not done(0):
        put(tiles.select("name", "nr", "nc", "data"), 0)
    run.manifest = dict.fromkeys(names_of(0), 0)  # a name for each tile
    size = {}
    by_wave: list[list[Task]] = []
    for t, w in zip(tasks, waves(tasks), strict=True):
        by_wave += [[]] * (w + 1 - len(by_wave))
        by_wave[w] = by_wave[w] + [t]

    def blocks(mine: list[Task], names: list[str]) -> DataFrame:
        """(seq, name, nr, nc, data) for the tasks' blocks among ``names``, all of which are there."""
        wanted = set(names)
        needs = spark.createDataFrame([(t.seq, x, run.manifest[x]) for t in mine for x in dict.fromkeys(t.ins) if x in wanted], "seq int, name string, made int")
        found = spark.read.schema(f"{STORE}, made int").parquet(*run.folders(names))
        # at most four rows a task of this wave
        return found.join(F.broadcast(needs), ["name", "made"]).select("seq", "name", "nr", "nc", "data")

    def prefetch(mine: list[Task], names: list[str], wave: int) -> DataFrame:
        start = time.time()
        held = blocks(mine, names).persist()
        held.count()
        run.trace.append(("read", wave, start - began, time.time() - began, len(names)))
        return held

    with ThreadPoolExecutor(1) as lane:
        ahead = None
        for w, mine in enumerate(by_wave):
            outs = {x for t in mine for x in t.outs}
            if done(w + 1):
                run.manifest.update(dict.fromkeys(names_of(w + 1), w + 1))
                continue
            needed = sorted({x for t in mine for x in t.ins if x in run.manifest})
            early, held = ahead.result() if ahead else ([], None)
            late = sorted(set(needed) - set(early))
            parts = ([held] if held is not None else []) + ([blocks(mine, late)] if late else [])
            # a row without data keeps tasks whose blocks aren't there
            idle = spark.createDataFrame([(t.seq, "", None, None, None) for t in mine], f"seq int, {STORE}")
            for p in parts:
                idle = idle.unionByName(p)
            arguments = {t.seq: (t.op, t.args, t.ins, t.outs) for t in mine}

            ahead = None
            if mode == "overlap" and w + 1 < len(by_wave) and not done(w + 2):
                after = by_wave[w + 1]
                there = sorted({x for t in after for x in t.ins if x in run.manifest and x not in outs})
                if there:
                    ahead = lane.submit(lambda a=after, n=there, w=w: (n, prefetch(a, n, w + 1)))
            start = time.time()
            put(idle.groupBy("seq").applyInArrow(worker(arguments, shapes, seed, b), STORE), w + 1)
            run.trace.append(("compute", w, start - began, time.time() - began, len(mine)))
            if held is not None:
                held.unpersist()
            run.manifest.update(dict.fromkeys(outs, w + 1))
            sizes = spark.read.parquet(f"{root}/version={w + 1}").select("name", (F.col("nr") * F.col("nc") * 8).alias("bytes")).collect()  # the wave's tiles
            size.update({r["name"]: r["bytes"] for r in sizes})
            for counted, names in ((run.read, [x for t in mine for x in t.ins if x in run.manifest]), (run.written, [x for t in mine for x in t.outs])):
                counted[0] += len(names)
                counted[1] += sum(size.get(x, 8 * b * b) for x in names)
    return run
