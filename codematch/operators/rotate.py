"""Rotations of residuals: per cluster from covariances, or found by alternation."""

from __future__ import annotations

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from codematch.operators import prep
from codematch.operators.encode import matrix, usable
from codematch.operators.model import CodeModel, nearest


def pca_allocate(cov: np.ndarray, parts: int) -> np.ndarray:
    """Rotation (rows are axes) that aligns with the principal axes and deals them to blocks of about equal products of eigenvalues."""
    values, axes = prep.eigen(cov)
    return axes[:, prep.allocate(values, parts)].T


def random_rotation(d: int, seed: int) -> np.ndarray:
    q, r = np.linalg.qr(np.random.default_rng(seed).normal(size=(d, d)))
    return q * np.sign(np.diag(r))


def cluster_covariances(df: DataFrame, model: CodeModel) -> tuple[np.ndarray, np.ndarray]:
    """(counts (halves, K), covariances (halves, K, dh, dh)) of residuals, by one aggregation with partial sums.

    Each map adds up its outer products by cluster; rows are (half, cluster, dimension), so the
    aggregation's parallelism grows with the number of clusters.
    """
    dh = model.dh

    def run(batches):
        n, s, o = np.zeros((model.halves, model.K)), np.zeros((model.halves, model.K, dh)), {}
        for batch in batches:
            if not batch.num_rows:
                continue
            x = model.prepare(matrix(batch, 1, model.raw))
            for h, c in enumerate(model.nearest_clusters(x).T):
                r = x[:, h * dh : (h + 1) * dh] - model.coarse[h][c]
                for i in np.unique(c):
                    own = r[c == i]
                    n[h, i] += len(own)
                    s[h, i] += own.sum(0)
                    o[h, int(i)] = o.get((h, int(i)), 0) + own.T @ own
        rows = [(h, i, j, float(n[h, i]), float(s[h, i, j]), v.tolist()) for (h, i), m in o.items() for j, v in enumerate(m)]
        if rows:
            yield pa.RecordBatch.from_arrays([pa.array(c, t) for c, t in zip(zip(*rows, strict=True), (pa.int32(), pa.int32(), pa.int32(), pa.float64(), pa.float64(), pa.list_(pa.float64())), strict=True)], names=["half", "cluster", "i", "n", "s", "o"])

    rows = usable(df).mapInArrow(run, "half int, cluster int, i int, n double, s double, o array<double>")
    total = rows.groupBy("half", "cluster", "i").agg(F.sum("n").alias("n"), F.sum("s").alias("s"), *(F.sum(F.get("o", F.lit(j))).alias(f"o{j}") for j in range(dh))).collect()
    n, s, o = np.zeros((model.halves, model.K)), np.zeros((model.halves, model.K, dh)), np.zeros((model.halves, model.K, dh, dh))
    for r in total:
        n[r.half, r.cluster], s[r.half, r.cluster, r.i], o[r.half, r.cluster, r.i] = r.n, r.s, [r[f"o{j}"] for j in range(dh)]
    few = np.maximum(n, 1)
    mean = s / few[..., None]
    return n, o / few[..., None, None] - mean[..., :, None] * mean[..., None, :]


def fit_local(df: DataFrame, model: CodeModel, method: str = "pca", seed: int = 0) -> np.ndarray | None:
    """Rotations (halves, K, dh, dh) of each cluster of each half.

    pca: from the cluster's covariance; clusters with fewer residuals than dimensions take
    that of their whole half. random and none are the arms of the ablation.
    """
    if method == "none":
        return None
    if method == "random":
        return np.stack([[random_rotation(model.dh, seed + h * model.K + i) for i in range(model.K)] for h in range(model.halves)])
    n, cov = cluster_covariances(df, model)
    out = np.zeros_like(cov)
    for h in range(model.halves):
        whole = (cov[h] * n[h][:, None, None]).sum(0) / max(n[h].sum(), 1)
        for i in range(model.K):
            out[h, i] = pca_allocate(cov[h, i] if n[h, i] >= model.dh else whole, model.m // model.halves)
    return out


def alternate(res: np.ndarray, m: int, k: int, iters: int = 20, seed: int = 0, start: np.ndarray | None = None) -> tuple[np.ndarray, np.ndarray, list[float]]:
    """(rotation, sub-codebooks (m, k, d / m), distortions) that minimize the error of quantizing rotated residuals.

    Codebooks move by a round of k-means with the rotation fixed; the rotation is the
    orthogonal solution of matching residuals to their reconstructions (an SVD). For a bounded sample.
    """
    n, d = res.shape
    w = d // m
    r = np.eye(d) if start is None else start
    x = res @ r.T
    books = np.stack([x[np.random.default_rng(seed + b).choice(n, k, replace=n < k), b * w : (b + 1) * w] for b in range(m)])
    history = []
    for _ in range(iters):
        x = res @ r.T
        y = np.empty_like(x)
        for b in range(m):
            part = x[:, b * w : (b + 1) * w]
            at = nearest(part, books[b])
            for j in np.unique(at):
                books[b, j] = part[at == j].mean(0)
            y[:, b * w : (b + 1) * w] = books[b][at]
        history.append(float(((x - y) ** 2).sum()))
        u, _, vt = np.linalg.svd(y.T @ res)
        r = u @ vt
    return r, books, history
