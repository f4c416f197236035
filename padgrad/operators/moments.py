"""Second and cross moments of devices, losses and gradients.

The one job that grows with the data is the moment pass. ``arrow`` sorts the rows of each
partition by device and sums ``X'X`` (its upper triangle) and ``X'Y`` in numpy, one device at a time, so a task
holds one matrix however many devices it meets. Partial sums leave in blocks of ``BLOCK`` matrix rows and
are added block by block as they stream in. At most (partitions x devices x d) half rows cross the
network, however many examples there are and however uneven devices are. ``sql`` makes a row for each
cell (for small d, and checkable in any SQL engine); its sums are partial before the shuffle too.

A model reaches executors as an Arrow broadcast, never as literals of a plan.
"""

from __future__ import annotations

from collections.abc import Iterator

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F
from pyspark.sql import types as T

from padgrad.functions.vectors import argmax

MOMENTS = "device int, i int, g array<double>, h array<double>"


#: Matrix rows of a partial sum that travel together.
BLOCK = 64
#: Numbers of raw rows that are multiplied at once.
HELD = 4_000_000


def _blocks(total: np.ndarray, second: bool) -> Iterator[tuple[int, np.ndarray]]:
    """Blocks of rows of ``[X'X, X'Y]`` from their own first column on (or of ``X'Y`` alone), flattened."""
    for k, at in enumerate(range(0, len(total), BLOCK)):
        yield k, total[at : at + BLOCK, at if second else 0 :].ravel()


_PARTS = pa.schema([("device", pa.int32()), ("block", pa.int32()), ("t", pa.list_(pa.float64()))])
_ROWS = pa.schema([("device", pa.int32()), ("i", pa.int32()), ("g", pa.list_(pa.float64())), ("h", pa.list_(pa.float64()))])


def _part(device: int, block: int, t: np.ndarray) -> pa.RecordBatch:
    return pa.RecordBatch.from_arrays([pa.array([device], pa.int32()), pa.array([block], pa.int32()), pa.ListArray.from_arrays(pa.array([0, len(t)], pa.int32()), pa.array(t))], schema=_PARTS)


def moment_parts(examples: DataFrame, d: int, c: int, second: bool = True) -> DataFrame:
    """``(device, block, t)``: partial sums, a block at a time; one d x (d + c) matrix in memory (d x c without ``second``)."""
    step = max(32, HELD // (d + c))

    def sums(batches):
        device, total = None, np.zeros((d, second * d + c))
        for b in batches:
            for at in range(0, b.num_rows, step):
                part = b.slice(at, step)
                dev = part.column("device").to_numpy()
                x = np.asarray(part.column("x").flatten(), float).reshape(-1, d)
                y = np.asarray(part.column("y").flatten(), float).reshape(-1, c)
                xy = np.hstack([x, y]) if second else y
                edges = np.flatnonzero(np.diff(dev, prepend=dev[0] - 1))
                for first, last in zip(edges, [*edges[1:], len(dev)], strict=True):
                    if device is not None and dev[first] != device:
                        yield from (_part(device, k, t) for k, t in _blocks(total, second))
                        total = np.zeros_like(total)
                    device = int(dev[first])
                    total += x[first:last].T @ xy[first:last]
        if device is not None:
            yield from (_part(device, k, t) for k, t in _blocks(total, second))

    rows = examples.select(F.col("device").cast("int").alias("device"), "x", "y").sortWithinPartitions("device")
    return rows.mapInArrow(sums, "device int, block int, t array<double>")


def added_parts(parts: DataFrame) -> DataFrame:
    """Sums of ``moment_parts``, streamed: a block in memory, however many parts there are."""

    def add(key: tuple, batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        total = None
        for b in batches:
            for k in range(b.num_rows):
                t = np.asarray(b.column("t")[k].values, float)
                total = t.copy() if total is None else total + t
        yield _part(key[0].as_py(), key[1].as_py(), total)

    return parts.groupBy("device", "block").applyInArrow(add, "device int, block int, t array<double>")


def mirrored(parts: DataFrame, d: int, c: int) -> DataFrame:
    """``MOMENTS`` from summed blocks: the lower triangle is filled in, one device a task."""

    def mirror(key: tuple, batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        g, h = np.zeros((d, d)), np.zeros((d, c))
        for b in batches:
            for block, t in zip(b.column("block").to_pylist(), b.column("t"), strict=True):
                at = block * BLOCK
                rows = np.asarray(t.values, float).reshape(-1, d - at + c)
                g[at : at + len(rows), at:], h[at : at + len(rows)] = rows[:, : d - at], rows[:, d - at :]
        g = np.triu(g) + np.triu(g, 1).T
        for at in range(0, d, BLOCK):
            n = len(g[at : at + BLOCK])
            cells = [pa.ListArray.from_arrays(pa.array(np.arange(0, n * w + 1, w), pa.int32()), pa.array(m[at : at + n].ravel())) for m, w in ((g, d), (h, c))]
            yield pa.RecordBatch.from_arrays([pa.array([key[0].as_py()] * n, pa.int32()), pa.array(range(at, at + n), pa.int32()), *cells], schema=_ROWS)

    return parts.groupBy("device").applyInArrow(mirror, MOMENTS)


def device_moments(examples: DataFrame, d: int, c: int, engine: str = "arrow", tasks: int | None = None) -> DataFrame:
    """``MOMENTS``: row i of each device's ``X'X`` and ``X'Y``. ``examples``: ``device, x, y`` (arrays of doubles).

    ``tasks`` (see ``planner.moment_tasks``) joins input partitions where a partial sum would outweigh their rows.
    """
    if engine == "sql":
        g = gram_cells(examples).groupBy("device", "i").agg(F.transform(F.array_sort(F.collect_list(F.struct("j", "v"))), lambda s: s["v"]).alias("g"))
        h = cross_cells(examples).groupBy("device", "i").agg(F.transform(F.array_sort(F.collect_list(F.struct("j", "v"))), lambda s: s["v"]).alias("h"))
        return g.join(h, ["device", "i"]).select("device", "i", "g", "h")

    # d (d + c) numbers a device, whatever the data's size
    rows = examples.coalesce(tasks) if tasks else examples
    return mirrored(added_parts(moment_parts(rows, d, c)), d, c)


def gram_cells(examples: DataFrame) -> DataFrame:
    """``(device, i, j, v)``: cells of ``X'X``; exact for integer vectors."""
    left = examples.select("device", "x", F.posexplode("x").alias("i", "a"))
    cells = left.select("device", "i", "a", F.posexplode("x").alias("j", "b"))
    return cells.groupBy("device", "i", "j").agg(F.sum(F.col("a") * F.col("b")).alias("v"))


def cross_cells(examples: DataFrame) -> DataFrame:
    """``(device, i, j, v)``: cells of ``X'Y``."""
    left = examples.select("device", "y", F.posexplode("x").alias("i", "a"))
    cells = left.select("device", "i", "a", F.posexplode("y").alias("j", "b"))
    return cells.groupBy("device", "i", "j").agg(F.sum(F.col("a") * F.col("b")).alias("v"))


def collect_moments(moments: DataFrame, devices: int, d: int, c: int) -> tuple[np.ndarray, np.ndarray]:
    """``(D, d, d)`` and ``(D, d, c)`` on the driver: D d (d + c) numbers, whatever the data's size."""
    g, h = np.zeros((devices, d, d)), np.zeros((devices, d, c))
    table = moments.toArrow()
    dev, i = table.column("device").to_numpy(), table.column("i").to_numpy()
    if len(dev):
        g[dev, i] = np.asarray(table.column("g").combine_chunks().flatten()).reshape(-1, d)
        h[dev, i] = np.asarray(table.column("h").combine_chunks().flatten()).reshape(-1, c)
    return g, h


def with_outputs(df: DataFrame, theta: np.ndarray, column: str = "x") -> DataFrame:
    """``df`` with ``out``: the array of the c numbers ``column Theta``; the model is broadcast once."""
    shared = df.sparkSession.sparkContext.broadcast(np.asarray(theta, float))
    kept = df.drop("out")
    d, c = theta.shape

    def multiply(batches):
        t, step = shared.value, max(32, HELD // (d + c))
        for b in batches:
            for at in range(0, b.num_rows, step):
                part = b.slice(at, step)
                out = np.asarray(part.column(column).flatten(), float).reshape(-1, d) @ t
                cells = pa.ListArray.from_arrays(pa.array(np.arange(0, out.size + 1, c), pa.int32()), pa.array(out.ravel()))
                yield pa.RecordBatch.from_arrays([*part.columns, cells], names=[*part.schema.names, "out"])

    return kept.mapInArrow(multiply, T.StructType([*kept.schema.fields, T.StructField("out", T.ArrayType(T.DoubleType()))]))


def squared_errors(examples: DataFrame, theta: np.ndarray) -> DataFrame:
    """``examples`` with ``error``: the squared distance of the outputs to ``y``."""
    distance = F.aggregate(F.zip_with("out", "y", lambda a, b: (a - b) * (a - b)), F.lit(0.0), lambda acc, v: acc + v)
    return with_outputs(examples, theta).withColumn("error", distance)


def local_loss(examples: DataFrame, theta: np.ndarray) -> DataFrame:
    """``(device, n, local_loss)``: half the mean squared error of each device, without regulariser."""
    rows = squared_errors(examples.select("device", "x", "y"), theta)
    return rows.groupBy("device").agg(F.count("*").alias("n"), (F.avg("error") / 2).alias("local_loss"))


def global_loss(examples: DataFrame, theta: np.ndarray, lam: float) -> DataFrame:
    """One row ``global_loss``."""
    reg = lam / 2 * float((theta**2).sum())
    return squared_errors(examples.select("x", "y"), theta).agg((F.avg("error") / 2 + reg).alias("global_loss"))


def combine_losses(local: DataFrame, theta: np.ndarray, lam: float) -> DataFrame:
    """The global loss from local ones, weighted by their share of examples."""
    reg = lam / 2 * float((theta**2).sum())
    return local.agg((F.sum(F.col("n") * F.col("local_loss")) / F.sum("n") + reg).alias("global_loss"))


def moment_loss(g: np.ndarray, h: np.ndarray, squares: float, m: int, theta: np.ndarray, lam: float) -> float:
    """The global loss from summed moments and the sum of squared targets."""
    gs, hs = g.sum(axis=0), h.sum(axis=0)
    return float((np.sum(theta * (gs @ theta)) - 2 * np.sum(theta * hs) + squares) / (2 * m) + lam / 2 * np.sum(theta**2))


def device_gradient(moments: DataFrame, theta: np.ndarray) -> DataFrame:
    """``(device, i, grad)``: row i of ``X'X Theta - X'Y``."""
    rows = with_outputs(moments, theta, "g")
    return rows.select("device", "i", F.zip_with("out", "h", lambda a, b: a - b).alias("grad"))


def device_gradient_rows(examples: DataFrame, theta: np.ndarray) -> DataFrame:
    """``(device, i, j, v)``: the same from raw rows, as mini-batches need."""
    d, c = theta.shape
    r = F.zip_with("out", "y", lambda a, b: a - b)
    rows = with_outputs(examples.select("device", "x", "y"), theta).select("device", "x", r.alias("y"))
    summed = added_parts(moment_parts(rows, d, c, second=False))  # X'(X Theta - Y) is a cross moment
    cells = summed.select("device", "block", F.posexplode("t").alias("at", "v"))
    return cells.select("device", (F.col("block") * BLOCK + F.expr(f"at div {c}")).cast("int").alias("i"), (F.col("at") % c).alias("j"), "v")


def aggregate_gradient(gradients: DataFrame, theta: np.ndarray, lam: float, m: int) -> np.ndarray:
    """Mean of device gradients plus ``lambda Theta`` on the driver: d c cells."""
    cells = gradients.select("i", F.posexplode("grad").alias("j", "v")).groupBy("i", "j").agg(F.sum("v").alias("v")).collect()
    out = lam * np.array(theta, float)
    for r in cells:
        out[r["i"], r["j"]] += r["v"] / m
    return out


def predict(examples: DataFrame, theta: np.ndarray) -> DataFrame:
    """``examples`` with ``predicted``: the class of the greatest output."""
    return with_outputs(examples, theta).withColumn("predicted", argmax(F.col("out"))).drop("out")


def ridge_solve(g: np.ndarray, h: np.ndarray, m: int, lam: float) -> np.ndarray:
    """The optimum in closed form, from summed moments."""
    return np.linalg.solve(g.sum(axis=0) / m + lam * np.eye(g.shape[1]), h.sum(axis=0) / m)


def max_eigen(g: np.ndarray, m: int, rounds: int = 200) -> float:
    """Largest eigenvalue of ``X'X / m`` by power iteration; steps above 2 over it diverge."""
    a = g.sum(axis=0) / m
    v = np.ones(len(a)) / np.sqrt(len(a))
    for _ in range(rounds):
        w = a @ v
        size = np.linalg.norm(w)
        if not size:
            return 0.0
        v = w / size
    return float(v @ a @ v)
