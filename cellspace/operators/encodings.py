"""Ways to hold a vector in a table: columns, packed bytes, arrays, the ML vector type and a slow custom type."""

from __future__ import annotations

import numpy as np
import pyarrow as pa
import pyarrow.compute as pc
from pyspark.ml.functions import array_to_vector, vector_to_array
from pyspark.sql import DataFrame
from pyspark.sql import functions as F


def encode(df: DataFrame, cols: list[str], kind: str) -> DataFrame:
    """``columns`` keeps the columns; else one column ``v``: ``array``, ``binary`` (little-endian doubles), ``udt`` (ML
    vector) or ``pickled`` (bytes of a custom serialiser)."""
    if kind == "columns":
        return df.select(*cols)
    if kind == "array":
        return df.select(F.array(*cols).alias("v"))
    if kind == "udt":
        return df.select(array_to_vector(F.array(*cols)).alias("v"))

    def pack(batches):
        for b in batches:
            x = np.stack([np.asarray(c) for c in b.columns], 1)
            flat = pa.py_buffer(np.ascontiguousarray(x).tobytes())
            offsets = pa.py_buffer((np.arange(len(x) + 1, dtype=np.int32) * 8 * x.shape[1]).tobytes())
            yield pa.RecordBatch.from_arrays([pa.Array.from_buffers(pa.binary(), len(x), [None, offsets, flat])], names=["v"])

    packed = df.select(*cols).mapInArrow(pack, "v binary")
    if kind == "binary":
        return packed

    @F.udf("binary")
    def custom(v):
        import pickle

        return bytearray(pickle.dumps(np.frombuffer(bytes(v), float).tolist()))

    return packed.select(custom("v").alias("v"))


def norm_sum(df: DataFrame, kind: str, cols: list[str]) -> DataFrame:
    """(total) of squared norms, read back from the encoding."""
    if kind == "columns":
        total = None
        for c in cols:
            term = F.col(c) * F.col(c)
            total = term if total is None else total + term
        return df.agg(F.sum(total).alias("total"))
    if kind in ("array", "udt"):
        v = F.col("v") if kind == "array" else vector_to_array("v")
        return df.agg(F.sum(F.aggregate(v, F.lit(0.0), lambda s, x: s + x * x)).alias("total"))
    if kind == "binary":

        def add(batches):
            for b in batches:
                col = pc.fill_null(b.column(0), b"")
                x = np.frombuffer(b"".join(col.to_pylist()), float)
                yield pa.RecordBatch.from_arrays([pa.array([float(x @ x)])], names=["t"])

        return df.mapInArrow(add, "t double").agg(F.sum("t").alias("total"))

    @F.udf("double")
    def slow(v):
        import pickle

        return sum(x * x for x in pickle.loads(bytes(v)))  # noqa: S301 - bytes written by ``encode`` in the same job

    return df.agg(F.sum(slow("v")).alias("total"))
