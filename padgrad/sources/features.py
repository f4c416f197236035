"""Features of examples: text histograms and random features of a Gaussian kernel."""

from __future__ import annotations

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F
from pyspark.sql import types as T

from padgrad.functions.keys import np_prf60, uniform


def text_histograms(docs: DataFrame, bins: int = 64, unit: bool = True) -> DataFrame:
    """``docs`` with ``x``: code points modulo ``bins`` over the whole text, of unit length or as counts; empty texts give zeros."""
    kept = docs.drop("x")
    schema = T.StructType([*kept.schema.fields, T.StructField("x", T.ArrayType(T.DoubleType()))])

    def count(batches):
        for b in batches:
            rows = np.zeros((b.num_rows, bins))
            for k, t in enumerate(b.column("text").to_pylist()):
                codes = np.frombuffer((t or "").encode("utf-32-le", "surrogatepass"), "<u4")
                rows[k] = np.bincount(codes % bins, minlength=bins)
            if unit:
                size = np.linalg.norm(rows, axis=1, keepdims=True)
                rows = rows / np.where(size > 0, size, 1)
            x = pa.ListArray.from_arrays(pa.array(np.arange(0, rows.size + 1, bins), pa.int32()), pa.array(rows.ravel()))
            yield pa.RecordBatch.from_arrays([*b.columns, x], names=[*b.schema.names, "x"])

    return kept.mapInArrow(count, schema)


def rbf_matrix(d_in: int, q: int, gamma: float, seed: int) -> tuple[np.ndarray, np.ndarray]:
    """Frequencies and phases, the same for every device of a seed."""
    g = np.random.Generator(np.random.Philox(seed))
    return g.standard_normal((d_in, q)) * np.sqrt(2 * gamma), g.uniform(0, 2 * np.pi, q)


def keyed_matrix(d_in: int, q: int, gamma: float, seed: str) -> tuple[np.ndarray, np.ndarray]:
    """The frequencies and phases of ``rbf_features_sql``: keyed hashes, two for each cell."""
    u = np.array([[[(np_prf60(seed, t, k, i) + 0.5) / 2.0**60 for k in range(q)] for i in range(d_in)] for t in ("w1", "w2")])
    phase = np.array([(np_prf60(seed, "b", k) + 0.5) / 2.0**60 for k in range(q)])
    return np.sqrt(-2 * np.log(u[0])) * np.cos(2 * np.pi * u[1]) * np.sqrt(2 * gamma), 2 * np.pi * phase


def rbf_features(df: DataFrame, d_in: int, q: int = 2000, gamma: float = 5.0, seed: int | str = 1, column: str = "x") -> DataFrame:
    """``column`` replaced by ``q`` random features ``sqrt(2/q) cos(x W + b)``; rows are mapped in Arrow batches. A text as seed draws by keyed hashes."""
    w, b = keyed_matrix(d_in, q, gamma, seed) if isinstance(seed, str) else rbf_matrix(d_in, q, gamma, seed)
    shared = df.sparkSession.sparkContext.broadcast((w, b))

    def embed(batches):
        w_, b_ = shared.value
        for batch in batches:
            for at in range(0, batch.num_rows, 480):
                part = batch.slice(at, 480)
                x = np.array(part.column(column).to_pylist(), float).reshape(-1, d_in)
                z = np.sqrt(2 / q) * np.cos(x @ w_ + b_)
                col = pa.ListArray.from_arrays(pa.array(np.arange(0, z.size + 1, q), pa.int32()), pa.array(z.ravel()))
                cols = [col if n == column else c for n, c in zip(part.schema.names, part.columns, strict=True)]
                yield pa.RecordBatch.from_arrays(cols, names=part.schema.names)

    schema = T.StructType([T.StructField(f.name, T.ArrayType(T.DoubleType()) if f.name == column else f.dataType) for f in df.schema.fields])
    return df.mapInArrow(embed, schema)


def rbf_features_sql(df: DataFrame, d_in: int, q: int, gamma: float, seed: str, column: str = "x") -> DataFrame:
    """The same map with frequencies drawn by the keyed hash: ``(id, q, v)``, a row for each feature.

    Normal draws are Box-Muller from two uniform ones, so SQL engines can check it.
    """
    spark = df.sparkSession
    cells = spark.range(q).select(F.col("id").cast("int").alias("q"), F.explode(F.sequence(F.lit(0), F.lit(d_in - 1))).alias("i"))
    u1, u2 = (uniform(F.lit(seed), F.lit(t), F.col("q"), F.col("i")) for t in ("w1", "w2"))
    w = F.sqrt(-2 * F.ln(u1)) * F.cos(2 * np.pi * u2) * float(np.sqrt(2 * gamma))
    weights = cells.select("q", "i", w.alias("w"))
    phase = 2 * np.pi * uniform(F.lit(seed), F.lit("b"), F.col("q"))
    values = df.select("id", F.posexplode(column).alias("i", "v"))
    sums = values.join(F.broadcast(weights), "i").groupBy("id", "q").agg(F.sum(F.col("v") * F.col("w")).alias("s"))
    return sums.select("id", "q", (float(np.sqrt(2 / q)) * F.cos(F.col("s") + phase)).alias("v"))
