"""Encoding: one narrow Arrow stage over (id, vec), the model sent along; no shuffle."""

from __future__ import annotations

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from codematch.operators.model import CodeModel

CODES = "id long, c1 int, c2 int, fine array<smallint>"
PROBES = "id long, half int, rnk int, c int, d double, fine array<smallint>"
_FINE = pa.list_(pa.int16())


def matrix(batch: pa.RecordBatch, column: int, d: int) -> np.ndarray:
    """A list column as a matrix; a null or a wrong length is an error."""
    col = batch.column(column)
    flat = col.flatten().to_numpy(zero_copy_only=False)
    if col.null_count or len(flat) != len(col) * d or not np.isfinite(flat).all():
        raise ValueError(f"vectors need {d} finite numbers each")
    return flat.reshape(len(col), d).astype(float)


def fine_column(f: np.ndarray) -> pa.Array:
    n, m = f.shape
    return pa.ListArray.from_arrays(pa.array(np.arange(0, (n + 1) * m, m) if m else np.zeros(n + 1), pa.int32()), pa.array(f.astype(np.int16).ravel()))


def usable(df: DataFrame) -> DataFrame:
    """Rows with a vector; null vectors are dropped before encoding (count them with vectors_missing)."""
    return df.where("vec IS NOT NULL").select("id", "vec")


def vectors_missing(df: DataFrame) -> DataFrame:
    return df.agg(F.count_if(F.col("vec").isNull()).alias("missing"))


def encode(df: DataFrame, model: CodeModel) -> DataFrame:
    """(id, c1, c2, fine); c2 is null with a single coarse space."""
    sent = df.sparkSession.sparkContext.broadcast(model)

    def run(batches):
        model = sent.value
        for batch in batches:
            if batch.num_rows:
                c, f = model.encode(matrix(batch, 1, model.raw))
                second = pa.array(c[:, 1].astype(np.int32)) if model.halves == 2 else pa.nulls(len(c), pa.int32())
                yield pa.RecordBatch.from_arrays([batch.column(0), pa.array(c[:, 0].astype(np.int32)), second, fine_column(f)], names=["id", "c1", "c2", "fine"])

    return usable(df).mapInArrow(run, CODES)


def encode_probes(df: DataFrame, model: CodeModel, probes: int) -> DataFrame:
    """(id, half, rnk, c, d, fine): the nearest clusters of each half, with the fine codes relative to each."""
    def run(batches):
        for batch in batches:
            if not batch.num_rows:
                continue
            x = model.prepare(matrix(batch, 1, model.raw))
            for h, dist in enumerate(model.half_distances(x)):
                order = np.argsort(dist, axis=1, kind="stable")[:, :probes]
                for r in range(order.shape[1]):
                    c = order[:, r]
                    n = len(c)
                    yield pa.RecordBatch.from_arrays([batch.column(0), pa.array(np.full(n, h, np.int32)), pa.array(np.full(n, r + 1, np.int32)), pa.array(c.astype(np.int32)), pa.array(dist[np.arange(n), c]), fine_column(model.fine(x, h, c))], names=["id", "half", "rnk", "c", "d", "fine"])

    return usable(df).mapInArrow(run, PROBES)


def coarse_codes(df: DataFrame, model: CodeModel) -> DataFrame:
    """(id, half, c, d, part): the nearest centroid of each half, its squared distance, and the vector's half."""

    def run(batches):
        for batch in batches:
            if not batch.num_rows:
                continue
            x = model.prepare(matrix(batch, 1, model.raw))
            for h, dist in enumerate(model.half_distances(x)):
                c = dist.argmin(1)
                n = len(c)
                yield pa.RecordBatch.from_arrays([batch.column(0), pa.array(np.full(n, h, np.int32)), pa.array(c.astype(np.int32)), pa.array(dist[np.arange(n), c]), pa.array(list(x[:, h * model.dh : (h + 1) * model.dh]), pa.list_(pa.float64()))], names=["id", "half", "c", "d", "part"])

    return usable(df).mapInArrow(run, "id long, half int, c int, d double, part array<double>")
