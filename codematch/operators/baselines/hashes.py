"""Hash functions that are compared with: random projections, rotated PCA signs, sequential projections, spectral functions, PCA signs.

Means, covariances, ranges and the sums of each iteration come from all rows; only the
sequential learner, which compares pairs of points, has at most TRAIN rows by hash for these
pairs. Each returns (d, bits, bits_of) for binary.encode.
"""

from __future__ import annotations

import hashlib

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from codematch.operators import prep
from codematch.operators.encode import matrix, usable

TRAIN = 20_000


def training_matrix(df: DataFrame, rows: int = TRAIN) -> np.ndarray:
    got = usable(df).orderBy(F.xxhash64("id"), "id").limit(rows).collect()
    return np.array([r.vec for r in sorted(got)], float)


def sign_planes(d: int, bits: int, seed: int = 0) -> np.ndarray:
    """(d, bits) of +1 / -1 by the parity of md5 of "seed:bit:dimension": the same in any engine."""
    return np.array([[1.0 if int(hashlib.md5(f"{seed}:{b}:{i}".encode()).hexdigest()[-1], 16) % 2 == 0 else -1.0 for b in range(bits)] for i in range(d)])


def lsh(d: int, bits: int, seed: int = 0, kind: str = "sign"):
    """Signs of random projections."""
    w = sign_planes(d, bits, seed) if kind == "sign" else np.random.default_rng(seed).normal(size=(d, bits))

    def bits_of(x):
        s = np.zeros((len(x), bits))
        for i in range(d):  # in the order of dimensions
            s += x[:, i, None] * w[i]
        return s >= 0

    return d, bits, bits_of


def pca_signs(df: DataFrame, bits: int, rotate: bool = True):
    """Signs of centred PCA dimensions; with rotate=False of the centred dimensions as they are."""
    _, mean, cov = prep.covariance(df)
    axes = prep.eigen(cov)[1][:, :bits] if rotate else np.eye(len(mean))[:, :bits]
    return len(mean), bits, lambda x: (x - mean) @ axes > 0 if rotate else (x - mean)[:, :bits] > 0


def _summed(df: DataFrame, d: int, of, shape: tuple[int, int]) -> np.ndarray:
    """The sum over all rows of of(matrix), an array of this shape: partial sums of tasks are added in their order."""

    def run(batches):
        total = np.zeros(shape)
        for batch in batches:
            for at in range(0, batch.num_rows, 4096):
                total += of(matrix(batch.slice(at, 4096), 1, d))
        yield pa.RecordBatch.from_arrays([pa.array([total.tobytes()], pa.binary())], names=["sum"])

    parts = usable(df).mapInArrow(run, "sum binary").withColumn("p", F.spark_partition_id()).orderBy("p").collect()
    return sum((np.frombuffer(bytes(r["sum"])).reshape(shape) for r in parts), np.zeros(shape))


def itq(df: DataFrame, bits: int, iters: int = 50, seed: int = 0, tolerance: float = 1e-4):
    """Signs of PCA dimensions after the rotation that brings points closest to the corners they fall to.

    A pass over all rows for each iteration; it ends early when the rotation hardly moves.
    """
    _, mean, cov = prep.covariance(df)
    axes = prep.eigen(cov)[1][:, :bits]
    r, _ = np.linalg.qr(np.random.default_rng(seed).normal(size=(axes.shape[1],) * 2))

    def toward(x, w, axes=axes, mean=mean):
        v = (x - mean) @ axes
        return v.T @ np.where(v @ w >= 0, 1.0, -1.0)

    for _ in range(iters):
        u, _, wt = np.linalg.svd(_summed(df, len(mean), lambda x, w=r: toward(x, w), r.shape))
        before, r = r, u @ wt
        if np.abs(r - before).max() < tolerance:
            break
    w = axes @ r
    return len(mean), w.shape[1], lambda x: (x - mean) @ w >= 0


def sequential(df: DataFrame, bits: int, margin: float = 0.15, eta: float = 0.5, seed: int = 0, pairs: int = 2000):
    """Projections one after another: each also repairs the cuts of the one before.

    Points just on both sides of the last threshold should have been together, points far
    apart on one side should not; their scatter is added to the covariance of what the chosen
    directions left.
    """
    _, mean, cov = prep.covariance(df)
    x = training_matrix(df) - mean
    rng, out = np.random.default_rng(seed), []
    adjust, left_over = np.zeros_like(cov), np.eye(len(mean))
    for _ in range(bits):
        w = prep.eigen(left_over.T @ cov @ left_over + eta * adjust)[1][:, 0]
        out.append(w)
        p = x @ w
        near = np.quantile(np.abs(p), margin)
        left, right = np.flatnonzero((p < 0) & (p > -near)), np.flatnonzero((p >= 0) & (p < near))
        adjust = np.zeros_like(cov)
        if len(left) and len(right):
            d = x[rng.choice(left, pairs)] - x[rng.choice(right, pairs)]
            adjust -= d.T @ d / pairs  # together: such differences are to be small along the next direction
        for side in (np.flatnonzero(p < -near), np.flatnonzero(p > near)):
            if len(side) > 1:
                d = x[rng.choice(side, pairs)] - x[rng.choice(side, pairs)]
                far = np.argsort(-(d * d).sum(1))[: pairs // 2]
                adjust += d[far].T @ d[far] / pairs
        left_over = left_over - np.outer(left_over @ w, w)
    w = np.array(out).T
    return x.shape[1], bits, lambda y: (y - mean) @ w >= 0


def spectral(df: DataFrame, bits: int):
    """Signs of the smoothest sinusoids along PCA dimensions, by the range of each."""
    _, mean, cov = prep.covariance(df)
    axes = prep.eigen(cov)[1][:, : min(bits, len(mean))]
    lo, hi = _ranges(df, mean, axes)
    span = np.maximum(hi - lo, 1e-9)
    modes = sorted((((j / span[a]) ** 2, a, j) for a in range(len(span)) for j in range(1, bits + 1)))[:bits]
    axis, freq = np.array([a for _, a, _ in modes]), np.array([j for _, _, j in modes])
    return len(mean), bits, lambda x: np.cos(((x - mean) @ axes - lo)[:, axis] / span[axis] * np.pi * freq) > 0


def _ranges(df: DataFrame, mean: np.ndarray, axes: np.ndarray) -> tuple[np.ndarray, np.ndarray]:
    """Least and largest value of all rows along each axis."""

    def run(batches):
        lo, hi = np.full(axes.shape[1], np.inf), np.full(axes.shape[1], -np.inf)
        for batch in batches:
            for at in range(0, batch.num_rows, 4096):
                v = (matrix(batch.slice(at, 4096), 1, len(mean)) - mean) @ axes
                lo, hi = np.minimum(lo, v.min(0)), np.maximum(hi, v.max(0))
        yield pa.RecordBatch.from_arrays([pa.array([lo.tobytes()], pa.binary()), pa.array([hi.tobytes()], pa.binary())], names=["lo", "hi"])

    parts = usable(df).mapInArrow(run, "lo binary, hi binary").collect()
    return np.min([np.frombuffer(bytes(r.lo)) for r in parts], 0), np.max([np.frombuffer(bytes(r.hi)) for r in parts], 0)
