"""Training of code models in all their variants.

Passes over the data: covariance (optional), coarse k-means (all halves at once), cluster
covariances for rotations, k-means of all blocks at once on rotated residuals. Only
codebooks and covariances reach the driver.
"""

from __future__ import annotations

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from codematch.operators import kmeans, prep, rotate
from codematch.operators.encode import matrix, usable
from codematch.operators.model import CodeModel

#: Rows per cluster, at most, that local codebooks are learnt from.
LOCAL_SAMPLE = 20_000


def training_sample(df: DataFrame, rows: int, seed: int = 0) -> DataFrame:
    """About `rows` rows by a hash of the id: the same for any partitioning."""
    n = max(df.count(), 1)
    if n <= rows:
        return df
    return df.where(F.pmod(F.xxhash64(F.lit(seed), "id"), F.lit(1_000_000)) < int(1_000_000 * rows / n))


def fit_pq(df: DataFrame, m: int, k: int, iters: int = 10, seed: int = 0, **how) -> CodeModel:
    """A plain product quantizer: one coarse cluster at the origin."""
    books = kmeans.fit(df, k, m, iters, seed, **how)
    return CodeModel(m=m, coarse=np.zeros((1, 1, books.shape[0] * books.shape[2])), sub=books)


def fit(df: DataFrame, K: int, m: int, k: int, halves: int = 2, rotation: str = "pca", codebooks: str = "global", pca: int | None = None, balanced: bool = True, iters: int = 10, seed: int = 0, init: str = "rows") -> CodeModel:
    """Coarse quantization in 1 or 2 spaces, a rotation for each cluster, and sub-codebooks, global or of each cluster.

    pca reduces to that many dimensions; balanced permutes dimensions so that the halves get
    about equal products of variance.
    """
    df = usable(df)
    mean = proj = perm = None
    if pca or (balanced and halves == 2):
        _, mu, cov = prep.covariance(df)
        if pca:
            values, axes = prep.eigen(cov)
            mean, proj, variance = mu, axes[:, :pca], values[:pca]
        else:
            variance = np.diag(cov)
        perm = prep.balance(variance, 2) if balanced and halves == 2 else None
    d = pca or len(df.first().vec)
    raw = len(mean) if mean is not None else d
    shape = CodeModel(m=m, coarse=np.zeros((halves, 1, d // halves)), sub=np.zeros((m, 1, d // m)), mean=mean, pca=proj, perm=perm)
    start = kmeans.seeds(df, halves, K, init, seed, prepare=shape.prepare)
    coarse, _ = kmeans.lloyd_rounds(df, start, iters, prepare=lambda b: shape.prepare(matrix(b, 1, raw)), stop=1e-4)
    base = CodeModel(m=m, coarse=coarse, sub=np.zeros((m, 1, d // m)), mean=mean, pca=proj, perm=perm)
    base.rot = rotate.fit_local(df, base, rotation, seed)

    def residuals(x: np.ndarray) -> np.ndarray:
        x = base.prepare(x)
        return np.concatenate([base.residual(x, h, c) for h, c in enumerate(base.nearest_clusters(x).T)], 1)

    if codebooks == "global":
        sub, _ = kmeans.lloyd_rounds(df, kmeans.seeds(df, m, k, init, seed + 1, prepare=residuals), iters, prepare=lambda b: residuals(matrix(b, 1, raw)), stop=1e-4)
    else:
        sub = _local_books(df, base, k, iters, raw)
    return CodeModel(m=m, coarse=coarse, sub=sub, rot=base.rot, mean=mean, pca=proj, perm=perm)


def _local_books(df: DataFrame, base: CodeModel, k: int, iters: int, raw: int) -> np.ndarray:
    """Sub-codebooks of each cluster, (halves, K, m / halves, k, w): each learnt in one task from a bounded sample."""
    per, w = base.m // base.halves, base.d // base.m

    def spread(batches):
        for batch in batches:
            if batch.num_rows:
                x = base.prepare(matrix(batch, 1, raw))
                for h, c in enumerate(base.nearest_clusters(x).T):
                    yield pa.RecordBatch.from_arrays([batch.column(0), pa.array(np.full(len(c), h, np.int32)), pa.array(c.astype(np.int32)), pa.array(list(base.residual(x, h, c)), pa.list_(pa.float64()))], names=["id", "half", "c", "r"])

    def learn(table: pa.Table) -> pa.Table:
        order = np.argsort(table.column("id").to_numpy(), kind="stable")
        x = np.array(table.column("r").to_pylist(), float)[order]
        out = []
        for b in range(per):
            part = x[:, b * w : (b + 1) * w]
            book = np.full((k, w), 1e6)
            book[: min(k, len(part))] = part[:k]
            for _ in range(iters):
                at = ((part[:, None] - book) ** 2).sum(2).argmin(1)
                for j in np.unique(at):
                    book[j] = part[at == j].mean(0)
            out += [{"half": table.column("half")[0].as_py(), "c": table.column("c")[0].as_py(), "b": b, "j": j, "v": v.tolist()} for j, v in enumerate(book)]
        return pa.Table.from_pylist(out, pa.schema([("half", pa.int32()), ("c", pa.int32()), ("b", pa.int32()), ("j", pa.int32()), ("v", pa.list_(pa.float64()))]))

    sample = training_sample(df, LOCAL_SAMPLE * base.K)
    rows = sample.mapInArrow(spread, "id long, half int, c int, r array<double>").groupBy("half", "c").applyInArrow(lambda t: learn(t), "half int, c int, b int, j int, v array<double>").collect()
    sub = np.full((base.halves, base.K, per, k, w), 1e6)
    for r in rows:
        sub[r.half, r.c, r.b, r.j] = r.v
    return sub
