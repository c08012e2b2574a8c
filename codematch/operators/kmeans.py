"""k-means for many sub-spaces at once: all blocks and halves advance in the same job.

A round is one narrow map that adds up, per batch, sums and counts by (part, centroid), and
one small aggregation of these; what the driver gets is as large as the codebooks.
"""

from __future__ import annotations

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from codematch.operators.encode import matrix, usable
from codematch.operators.model import nearest, squared


def _round(df: DataFrame, books: np.ndarray, prepare=None) -> tuple[np.ndarray, np.ndarray, float]:
    """(sums (parts, k, w), counts (parts, k), distortion) of one assignment of all rows."""
    parts, k, w = books.shape
    d = parts * w

    def run(batches):
        sums, counts, error = np.zeros(books.shape), np.zeros((parts, k)), 0.0
        for batch in batches:
            if not batch.num_rows:
                continue
            x = prepare(batch) if prepare else matrix(batch, 1, d)
            for p in range(parts):
                own = x[:, p * w : (p + 1) * w]
                dist = squared(own, books[p])
                at = dist.argmin(1)
                for i in range(w):
                    sums[p, :, i] += np.bincount(at, own[:, i], k)
                counts[p] += np.bincount(at, minlength=k)
                error += float(dist[np.arange(len(x)), at].sum())
        yield pa.RecordBatch.from_pydict({"part": pa.array(np.repeat(np.arange(parts), k).astype(np.int32)), "idx": pa.array(np.tile(np.arange(k), parts).astype(np.int32)), "n": counts.ravel(), "s": pa.array(list(sums.reshape(-1, w)), pa.list_(pa.float64())), "e": np.r_[error, np.zeros(parts * k - 1)]})

    rows = usable(df).mapInArrow(run, "part int, idx int, n double, s array<double>, e double")
    total = rows.groupBy("part", "idx").agg(F.sum("n").alias("n"), F.sum("e").alias("e"), *(F.sum(F.get("s", F.lit(i))).alias(f"s{i}") for i in range(w))).collect()
    sums, counts, error = np.zeros(books.shape), np.zeros((parts, k)), 0.0
    for r in total:
        counts[r.part, r.idx] = r.n
        sums[r.part, r.idx] = [r[f"s{i}"] for i in range(w)]
        error += r.e
    return sums, counts, error


def lloyd_rounds(df: DataFrame, start: np.ndarray, iters: int, empty: str = "keep", stop: float = 0.0, prepare=None, history: list | None = None) -> tuple[np.ndarray, np.ndarray]:
    """(codebooks, counts of the last assignment) after `iters` rounds from start (parts, k, w).

    An empty cluster keeps its centroid, or with empty="split" takes that of the largest
    cluster, moved a little. Stops when the distortion falls by less than the share `stop`.
    """
    books, counts, last = np.array(start, float), np.zeros(start.shape[:2]), None
    for _ in range(iters):
        sums, counts, error = _round(df, books, prepare)
        if history is not None:
            history.append(error)
        new = np.where(counts[..., None] > 0, sums / np.maximum(counts, 1)[..., None], books)
        if empty == "split":
            for p, i in zip(*np.nonzero(counts == 0), strict=True):
                new[p, i] = new[p, counts[p].argmax()] * (1 + 1e-3)
        books = new
        if last is not None and stop and last - error <= stop * max(last, 1e-300):
            break
        last = error
    return books, counts


def seeds(df: DataFrame, parts: int, k: int, init: str = "rows", seed: int = 0, prepare=None, sample: int = 20_000) -> np.ndarray:
    """Start codebooks (parts, k, w) from at most `sample` rows by hash: the first rows, or k-means++ ("kpp"), or a weighted re-cut of it ("parallel")."""
    picked = usable(df).orderBy(F.xxhash64(F.lit(seed), "id"), "id").limit(max(k, sample if init != "rows" else k))
    rows = sorted((r.id, r.vec) for r in picked.collect())
    x = np.array([v for _, v in rows], float)
    if prepare:
        x = prepare(x)
    if len(x) < k:
        raise ValueError(f"{k} centroids need as many rows; {len(x)} are there")
    w = x.shape[1] // parts
    rng, out = np.random.default_rng(seed), []
    for p in range(parts):
        own = x[:, p * w : (p + 1) * w]
        if init == "rows":
            out.append(own[:k])
            continue
        book = [own[rng.integers(len(own))]]
        dist = ((own - book[0]) ** 2).sum(1)
        many = k if init == "kpp" else 3 * k
        while len(book) < many:
            pick = own[rng.choice(len(own), p=dist / dist.sum()) if dist.sum() > 0 else rng.integers(len(own))]
            book.append(pick)
            dist = np.minimum(dist, ((own - pick) ** 2).sum(1))
        book = np.array(book)
        if init == "parallel":
            weight = np.bincount(nearest(own, book), minlength=len(book))
            book = book[np.argsort(-weight, kind="stable")[:k]]
        out.append(book)
    return np.stack(out)


def fit(df: DataFrame, k: int, parts: int = 1, iters: int = 10, seed: int = 0, init: str = "rows", empty: str = "keep", stop: float = 1e-4, history: list | None = None) -> np.ndarray:
    """Codebooks (parts, k, d / parts) of (id, vec)."""
    return lloyd_rounds(df, seeds(df, parts, k, init, seed), iters, empty, stop, history=history)[0]
