"""Gaussian projection of points and queries."""

from __future__ import annotations

import random

from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

from innersearch.functions import vectors as V

#: Up to this many coordinates the matrix is put into the plan as literals; above, numpy blocks.
LITERAL_CELLS = 4096


def gaussian_matrix(m: int, d: int, seed: int = 42) -> tuple[tuple[float, ...], ...]:
    """m standard normal vectors of d coordinates, rounded so that every engine reads the same text."""
    r = random.Random(seed)
    return tuple(tuple(round(r.gauss(0, 1), 6) for _ in range(d)) for _ in range(m))


def projected(v: str, matrix) -> Column:
    return F.array(*[V.dot(F.col(v), V.literal(row)) for row in matrix])


def _blocks(df: DataFrame, v: str, matrix, out: str) -> DataFrame:
    import numpy as np
    from pyspark.sql import types as T

    w = np.array(matrix).T
    at = df.columns.index(v)
    schema = T.StructType([*df.schema.fields, T.StructField(out, T.ArrayType(T.DoubleType()))])

    def run(batches):
        import pyarrow as pa

        for b in batches:
            flat = b.column(at).flatten().to_numpy().reshape(b.num_rows, -1)
            y = np.round(flat @ w, 12)
            arr = pa.ListArray.from_arrays(np.arange(0, y.size + 1, y.shape[1], dtype=np.int32), pa.array(y.ravel()))
            yield pa.RecordBatch.from_arrays([*b.columns, arr], names=schema.fieldNames())

    return df.mapInArrow(run, schema)


def summed(df: DataFrame, v: str, matrix, out: str) -> DataFrame:
    """df with the column that projected() gives, by whole batches: products are summed in its order, so the values are the same
    to the last bit."""
    import numpy as np
    from pyspark.sql import types as T

    w = np.array(matrix)
    at = df.columns.index(v)
    schema = T.StructType([*df.schema.fields, T.StructField(out, T.ArrayType(T.DoubleType()))])
    names = schema.fieldNames()

    def run(batches):
        import pyarrow as pa

        for b in batches:
            there = b.column(at).is_valid().to_numpy(zero_copy_only=False)
            x = b.column(at).flatten().to_numpy().reshape(there.sum(), w.shape[1])
            y = np.zeros((len(x), len(w)))
            for j in range(w.shape[1]):
                y += x[:, j, None] * w[:, j]
            ends = np.concatenate([[0], np.cumsum(there * len(w))]).astype(np.int32)
            yield pa.RecordBatch.from_arrays([*b.columns, pa.ListArray.from_arrays(pa.array(ends), pa.array(y.ravel()), mask=pa.array(~there))], names=names)

    return df.mapInArrow(run, schema)


def project_points(points: DataFrame, matrix) -> DataFrame:
    """points with pv (projection), n2 (squared 2-norm), n1 (1-norm)."""
    if len(matrix) * len(matrix[0]) <= LITERAL_CELLS:
        out = points.withColumn("pv", projected("v", matrix))
    else:
        out = _blocks(points, "v", matrix, "pv")
    return out.withColumn("n2", V.sq("v")).withColumn("n1", V.l1("v"))


def project_queries(queries: DataFrame, matrix) -> DataFrame:
    """queries with qpv, qn2, qn1."""
    q = queries.withColumn("qpv", projected("qv", matrix)) if len(matrix) * len(matrix[0]) <= LITERAL_CELLS else _blocks(queries, "qv", matrix, "qpv")
    return q.withColumn("qn2", V.sq("qv")).withColumn("qn1", V.l1("qv"))


def ratio_sample(pairs: DataFrame, m: int, d: int, seeds: range) -> DataFrame:
    """seed, id, ratio: squared projected over squared true distance of pairs(id, a, b) for many matrices."""
    out = None
    for s in seeds:
        w = gaussian_matrix(m, d, s)
        one = pairs.select(F.lit(s).alias("seed"), "id", (V.dist2(projected("a", w), projected("b", w)) / V.dist2("a", "b")).alias("ratio"))
        out = one if out is None else out.unionByName(one)
    return out
