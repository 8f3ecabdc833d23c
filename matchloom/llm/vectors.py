"""Embedding columns as fixed-width bytes, and groups of equal vectors."""

from __future__ import annotations

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame, functions as F


def decode(blobs: list[bytes], kind: type = np.float64) -> np.ndarray:
    """Rows of doubles from blobs of that kind, which all have the same length."""
    return np.frombuffer(b"".join(blobs), kind).reshape(len(blobs), -1).astype(np.float64, copy=False) if blobs else np.zeros((0, 0))


def kept_kind(vectors: DataFrame, vector_col: str = "embedding") -> type:
    """The narrowest kind of number that keeps the column's components as they are."""
    return np.float32 if vectors.schema[vector_col].dataType.simpleString() == "array<float>" else np.float64


def packed(vectors: DataFrame, id_col: str = "vec_id", vector_col: str = "embedding", kind: type = np.float64) -> DataFrame:
    """``(vec_id, vec)``: components of that kind as bytes, or null where the vector is null, empty, zero or
    holds a null or a component that is not finite. -0.0 counts as 0.0."""

    def run(batches):
        for batch in batches:
            column = batch.column(1)
            out = []
            flat = column.flatten()
            plain = flat.to_numpy(zero_copy_only=False).astype(kind)
            sizes = np.diff(column.offsets.to_numpy()) if len(column) else np.zeros(0, int)
            sizes = np.where(column.is_null().to_numpy(zero_copy_only=False), 0, sizes)
            ends = np.cumsum(sizes)
            for a, b in zip((ends - sizes).tolist(), ends.tolist()):
                v = plain[a:b] + kind(0.0)
                out.append(v.tobytes() if b > a and np.isfinite(v).all() and v.any() else None)
            yield pa.RecordBatch.from_arrays([batch.column(0), pa.array(out, pa.binary())], names=["vec_id", "vec"])

    chosen = vectors.select(F.col(id_col).cast("long").alias("vec_id"), F.col(vector_col).cast("array<double>").alias("v"))
    return chosen.mapInArrow(run, "vec_id long, vec binary")


def distinct_vectors(rows: DataFrame) -> DataFrame:
    """``(id, copies, vec)``: each vector once, under its smallest vec_id."""
    return rows.where("vec is not null and vec_id is not null").groupBy("vec").agg(F.min("vec_id").alias("id"), F.count("*").alias("copies"))
