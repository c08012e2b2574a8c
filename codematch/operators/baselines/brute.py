"""Exact search: the query set against all rows, in blocks; the source of ground truth."""

from __future__ import annotations

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from codematch.operators.encode import matrix, usable
from codematch.operators.model import squared
from codematch.operators.search import top

MOST_QUERIES = 100_000


def _queries(queries: DataFrame) -> tuple[np.ndarray, np.ndarray]:
    rows = sorted((r.id, r.vec) for r in usable(queries).limit(MOST_QUERIES + 1).collect())
    if len(rows) > MOST_QUERIES:
        raise ValueError(f"more than {MOST_QUERIES} queries: search in several sets")
    return np.array([i for i, _ in rows], np.int64), np.array([v for _, v in rows], float)


def _scan(queries: DataFrame, items: DataFrame, keep: int | None) -> DataFrame:
    """Squared distances of a bounded query set to all rows; with keep, each batch's nearest `keep` of each query."""
    ids, q = _queries(queries)

    def run(batches):
        for batch in batches:
            for at in range(0, batch.num_rows, 1024):
                part = batch.slice(at, 1024)
                if not len(ids):
                    continue
                x, own = matrix(part, 1, q.shape[1]), part.column(0).to_numpy()
                order = np.argsort(own, kind="stable")
                x, own = x[order], own[order]
                for lo in range(0, len(ids), 256):
                    d = squared(q[lo : lo + 256], x)
                    n = len(own) if keep is None else min(keep, len(own))
                    near = np.argsort(d, axis=1, kind="stable")[:, :n]
                    yield pa.RecordBatch.from_pydict({"qid": np.repeat(ids[lo : lo + 256], n), "id": own[near].ravel(), "score": np.take_along_axis(d, near, 1).ravel()})

    return usable(items).mapInArrow(run, "qid long, id long, score double")


def distances(queries: DataFrame, items: DataFrame) -> DataFrame:
    """(qid, id, score = squared distance) of every query and row."""
    return _scan(queries, items, None)


def knn(queries: DataFrame, items: DataFrame, R: int, exclude_self: bool = True) -> DataFrame:
    """(qid, id, score, rnk): the R nearest rows of each query, ties by id."""
    met = _scan(queries, items, R + 1 if exclude_self else R)
    return top(met.where("qid <> id") if exclude_self else met, R, rising=True)


def kmeans_clusters(df: DataFrame, K: int, seed: int = 1, kind: str = "kmeans") -> DataFrame:
    """(id, cluster) by the engine's own k-means or bisecting k-means: reference clusters."""
    from pyspark.ml.clustering import BisectingKMeans, KMeans
    from pyspark.ml.functions import array_to_vector

    rows = usable(df).select("id", array_to_vector("vec").alias("features"))
    make = KMeans if kind == "kmeans" else BisectingKMeans
    return make(k=K, seed=seed).fit(rows).transform(rows).select("id", F.col("prediction").alias("cluster"))


def random_rank(queries: DataFrame, items: DataFrame, R: int, seed: int = 0) -> DataFrame:
    """(qid, id, score, rnk): rows in the order of a hash, the floor of every ranking. An error beyond a bounded query set, as with knn."""
    q = queries.select(F.col("id").alias("qid"))
    if q.limit(MOST_QUERIES + 1).count() > MOST_QUERIES:
        raise ValueError(f"more than {MOST_QUERIES} queries: search in several sets")
    scored = F.broadcast(q).crossJoin(items.select("id")).where("qid <> id").withColumn("score", F.conv(F.substring(F.md5(F.concat_ws(":", F.lit(seed), "qid", "id")), 1, 8), 16, 10).cast("double"))
    return top(scored, R, rising=True)
