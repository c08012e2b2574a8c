"""Scores: hits, quantized distances, cell weights. All but ADC tables are column expressions."""

from __future__ import annotations

from functools import reduce

import numpy as np
import pyarrow as pa
from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

from codematch.operators.encode import matrix, usable
from codematch.operators.model import CodeModel, squared


def _equal(a: Column, b: Column, places: range) -> Column:
    return reduce(lambda x, y: x + y, ((F.get(a, F.lit(i)) == F.get(b, F.lit(i))).cast("int") for i in places), F.lit(0))


def hits(a: Column, b: Column, m: int) -> Column:
    """Number of equal fine codes; a sum that is code-generated, without a lambda."""
    return _equal(a, b, range(m))


def hits_pair(x: str, y: str, m: int) -> Column:
    """Hits of two code rows (aliases x and y): each half counts only where its coarse codes are equal."""
    c = lambda t, n: F.col(f"{t}.{n}")
    one, two = (F.when(c(x, n) == c(y, n), _equal(c(x, "fine"), c(y, "fine"), r)).otherwise(F.lit(0)) for n, r in (("c1", range(m // 2)), ("c2", range(m // 2, m))))
    return one + two


def hits_single(x: str, y: str, m: int) -> Column:
    """Hits with one coarse space: only inside a cluster."""
    return F.when(F.col(f"{x}.c1") == F.col(f"{y}.c1"), hits(F.col(f"{x}.fine"), F.col(f"{y}.fine"), m)).otherwise(F.lit(0))


def cell_weight(d: Column, kind: str = "exp", scale: float = 1.0, lam: float = 1.0) -> Column:
    """Weight of a visited cell by its distance, in (0, lam]: it orders points with equal hits and outvotes no hit."""
    if kind == "none":
        return F.lit(0.0)
    return F.exp(-d / scale) * lam


def weighted(d: Column, n: Column, kind: str = "exp", scale: float = 1.0, lam: float = 1.0) -> Column:
    return cell_weight(d, kind, scale, lam) + n


def sdc_tables(model: CodeModel) -> np.ndarray:
    """Squared distances between the sub-centroids of each block: (m, k, k)."""
    return np.stack([squared(b, b) for b in model.sub])


def sdc(a: Column, b: Column, tables: np.ndarray) -> Column:
    """Symmetric distance: both sides quantized; m look-ups in a table that stays small."""
    m, k, _ = tables.shape
    flat = F.lit(np.round(tables, 12).ravel().tolist())
    place = lambda j: F.lit(j * k * k) + F.get(a, F.lit(j)).cast("int") * k + F.get(b, F.lit(j)).cast("int")
    return reduce(lambda x, y: x + y, (F.get(flat, place(j)) for j in range(m)), F.lit(0.0))


def adc_tables(queries: DataFrame, model: CodeModel) -> DataFrame:
    """(qid, table): squared distances of each query's blocks to all sub-centroids, m * k numbers. For a model without coarse residuals."""
    w = model.d // model.m

    def run(batches):
        for batch in batches:
            if batch.num_rows:
                x = matrix(batch, 1, model.d)
                t = np.concatenate([squared(x[:, j * w : (j + 1) * w], model.sub[j]) for j in range(model.m)], 1)
                yield pa.RecordBatch.from_arrays([batch.column(0), pa.array(list(t), pa.list_(pa.float64()))], names=["qid", "table"])

    return usable(queries).mapInArrow(run, "qid long, table array<double>")


def adc(table: Column, fine: Column, m: int, k: int) -> Column:
    """Asymmetric distance: a raw query's table, looked up by codes."""
    return reduce(lambda x, y: x + y, (F.get(table, F.lit(j * k) + F.get(fine, F.lit(j)).cast("int")) for j in range(m)), F.lit(0.0))
