"""Preparation of vectors: covariance in one pass, PCA, and permutations that balance variance."""

from __future__ import annotations

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame

from codematch.operators.encode import usable


def covariance(df: DataFrame, groups: int = 16) -> tuple[int, np.ndarray, np.ndarray]:
    """(n, mean, population covariance): partial sums by partition, added by a few tasks, then on the driver."""

    def partial(batches):
        total, d = None, 0
        for batch in batches:
            if batch.num_rows:
                flat = batch.column(1).flatten().to_numpy(zero_copy_only=False)
                x = flat.reshape(batch.num_rows, -1).astype(float)
                d = x.shape[1]
                s = np.r_[len(x), x.sum(0), (x.T @ x).ravel()]
                total = s if total is None else total + s
        if total is not None:
            yield pa.RecordBatch.from_pydict({"s": [total.tobytes()]})

    def add(batches):
        total = None
        for batch in batches:
            for b in batch.column(0).to_pylist():
                s = np.frombuffer(b)
                total = s.copy() if total is None else total + s
        if total is not None:
            yield pa.RecordBatch.from_pydict({"s": [total.tobytes()]})

    parts = usable(df).mapInArrow(partial, "s binary").repartition(groups).mapInArrow(add, "s binary").collect()
    if not parts:
        raise ValueError("no vectors")
    s = np.sum([np.frombuffer(bytes(p.s)) for p in parts], axis=0)
    d = int((np.sqrt(4 * len(s) - 3) - 1) / 2)
    n, mean = int(s[0]), s[1 : d + 1] / s[0]
    return n, mean, s[d + 1 :].reshape(d, d) / n - np.outer(mean, mean)


def eigen(cov: np.ndarray) -> tuple[np.ndarray, np.ndarray]:
    """(eigenvalues falling, eigenvectors as columns with the largest entry positive)."""
    values, vectors = np.linalg.eigh(cov)
    values, vectors = values[::-1], vectors[:, ::-1]
    sign = np.sign(vectors[np.abs(vectors).argmax(0), np.arange(vectors.shape[1])])
    return values, vectors * np.where(sign == 0, 1, sign)


def pca(df: DataFrame, d: int) -> tuple[np.ndarray, np.ndarray]:
    """(mean, projection (d0, d)) on the d strongest directions of the collection."""
    _, mean, cov = covariance(df)
    return mean, eigen(cov)[1][:, :d]


def allocate(eigenvalues: np.ndarray, parts: int) -> np.ndarray:
    """Permutation of axes: each axis, by falling eigenvalue, goes to the part with room whose product is smallest."""
    v = np.log(np.maximum(np.asarray(eigenvalues, float), 1e-12))
    v = v - v.min() + 1e-9  # products compare as sums; every axis adds something
    room, load, own = len(v) // parts, np.zeros(parts), [[] for _ in range(parts)]
    for i in np.argsort(-v, kind="stable"):
        open_ = [p for p in range(parts) if len(own[p]) < room]
        p = min(open_, key=lambda q: (load[q], q))
        own[p].append(int(i))
        load[p] += v[i]
    return np.array([i for part in own for i in part])


def balance(variance: np.ndarray, parts: int = 2) -> np.ndarray:
    """Permutation of dimensions that gives the parts about equal products of variance."""
    return allocate(variance, parts)


def snake(variance: np.ndarray) -> np.ndarray:
    """The same by turns 1, 2, 2, 1 over falling variance: halves from ranks alone."""
    order = np.lexsort((np.arange(len(variance)), -np.asarray(variance)))
    ranks = np.arange(len(order)) % 4
    return np.r_[order[(ranks == 0) | (ranks == 3)], order[(ranks == 1) | (ranks == 2)]]
