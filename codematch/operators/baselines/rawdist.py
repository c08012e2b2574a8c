"""Ranking by quantized distance instead of hits, over the same visited cells."""

from __future__ import annotations

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from codematch.operators import score, search
from codematch.operators.encode import matrix, usable
from codematch.operators.model import CodeModel, squared
from codematch.sources.io import materialize


def half_tables(queries: DataFrame, model: CodeModel, cells: DataFrame, symmetric: bool) -> DataFrame:
    """(qid, half, c, table): distances from a query's residual to all sub-centroids of a half, relative to each cluster that it visits; from its quantized residual if symmetric.

    cells: (qid, c1, c2) as visited; other clusters get no table.
    """
    per, w = model.m // model.halves, model.d // model.m
    sent = queries.sparkSession.sparkContext.broadcast(model)
    seen = cells.groupBy("qid").agg(F.sort_array(F.collect_set("c1")).alias("h0"), F.sort_array(F.collect_set("c2")).alias("h1"))

    def tables(model: CodeModel, x: np.ndarray, h: int, c: np.ndarray) -> np.ndarray:
        r, out = model.residual(x, h, c), []
        for b in range(per):
            book = model.sub[h * per + b]
            d = squared(r[:, b * w : (b + 1) * w], book)
            out.append(squared(book[d.argmin(1)], book) if symmetric else d)
        return np.concatenate(out, 1)

    def run(batches):
        model = sent.value
        for batch in batches:
            for lo in range(0, batch.num_rows, 64):
                part = batch.slice(lo, 64)
                x, qid = model.prepare(matrix(part, 1, model.raw)), part.column(0).to_numpy()
                for h in range(model.halves):
                    visited = part.column(2 + h).to_pylist()
                    at, c = np.repeat(np.arange(len(x)), [len(v) for v in visited]), np.array([k for v in visited for k in v], np.int64)
                    for i in range(0, len(at), 512):
                        t = tables(model, x[at[i : i + 512]], h, c[i : i + 512])
                        yield pa.RecordBatch.from_arrays([pa.array(qid[at[i : i + 512]]), pa.array(np.full(len(t), h, np.int32)), pa.array(c[i : i + 512].astype(np.int32)), pa.array(list(t), pa.list_(pa.float64()))], names=["qid", "half", "c", "table"])

    q = usable(queries).join(seen, F.col("id") == F.col("qid")).select("id", "vec", "h0", "h1")
    return q.mapInArrow(run, "qid long, half int, c int, table array<double>")


def knn(queries: DataFrame, model: CodeModel, codes: DataFrame, R: int, T: int, symmetric: bool = False) -> DataFrame:
    """(qid, id, score, rnk): the R nearest of the T candidates by quantized distance; in one or two coarse spaces."""
    cells = materialize(search.visited_cells(queries, model, search.cell_sizes(codes), T), "cells")
    t = half_tables(queries, model, cells, symmetric)
    half = lambda h, c: t.where(f"half = {h}").select("qid", F.col("c").alias(c), F.col("table").alias(f"t{h}"))
    cells = cells.join(half(0, "c1"), ["qid", "c1"])
    if model.halves == 2:
        cells = cells.join(half(1, "c2"), ["qid", "c2"]).withColumn("t0", F.concat("t0", "t1"))
    met = search.same_cell(search.small(cells.select("qid", "c1", "c2", F.col("t0").alias("table")), 50_000), codes, model).where("qid <> id")
    return search.top(met.select("qid", "id", score.adc(F.col("table"), F.col("fine"), model.m, model.k).alias("score")), R, rising=True)


def pq_scan(queries: DataFrame, items: DataFrame, model: CodeModel, R: int, symmetric: bool = False) -> DataFrame:
    """Exhaustive search of a plain product quantizer."""
    from codematch.operators.encode import encode

    t = score.adc_tables(queries, model)
    if symmetric:
        codes = encode(queries, model).select(F.col("id").alias("qid"), F.col("fine").alias("qf"))
        met = search.small(codes, 50_000).crossJoin(encode(items, model)).select("qid", "id", score.sdc(F.col("qf"), F.col("fine"), score.sdc_tables(model)).alias("score"))
    else:
        met = search.small(t, 50_000).crossJoin(encode(items, model)).select("qid", "id", score.adc(F.col("table"), F.col("fine"), model.m, model.k).alias("score"))
    return search.top(met.where("qid <> id"), R, rising=True)
