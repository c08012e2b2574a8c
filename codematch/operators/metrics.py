"""Accuracy and cost measures: small aggregates over result frames."""

from __future__ import annotations

import time

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame, Window
from pyspark.sql import functions as F

from codematch.operators.encode import matrix, usable
from codematch.operators.model import CodeModel


def recall_at(results: DataFrame, truth: DataFrame, depths: list[int]) -> DataFrame:
    """(R, recall): share of the queries of truth(qid, id) whose true neighbour is among the first R of results(qid, id, rnk)."""
    found = truth.join(results.select("qid", "id", "rnk"), ["qid", "id"], "left")
    wide = found.agg(*(F.avg(F.when(F.col("rnk") <= r, 1.0).otherwise(0.0)).alias(str(r)) for r in depths))
    return wide.select(F.explode(F.array(*(F.struct(F.lit(r).alias("R"), F.col(f"`{r}`").alias("recall")) for r in depths))).alias("x")).select("x.R", F.round("x.recall", 6).alias("recall"))


def precision_at(results: DataFrame, relevant: DataFrame, depths: list[int], group: str = "set_id") -> DataFrame:
    """(group, P, precision): relevant share of the first P of results(group, id, rnk); relevant has (group, id)."""
    marked = results.join(relevant.select(group, "id").distinct().withColumn("hit", F.lit(1.0)), [group, "id"], "left")
    wide = marked.groupBy(group).agg(*(F.avg(F.when(F.col("rnk") <= p, F.coalesce("hit", F.lit(0.0)))).alias(str(p)) for p in depths))
    return wide.select(group, F.explode(F.array(*(F.struct(F.lit(p).alias("P"), F.round(F.col(f"`{p}`"), 6).alias("precision")) for p in depths))).alias("x")).select(group, "x.P", "x.precision")


def pair_pr(pairs: DataFrame, truth: DataFrame, thresholds: list[int], rising: bool = True) -> DataFrame:
    """(threshold, found, correct, precision, recall) of pairs(a, b, s) against truth(a, b).

    Pairs count if s >= threshold (<= if not rising). Pairs that are never named are
    negatives; they are not enumerated.
    """
    marked = pairs.join(truth.select("a", "b").distinct().withColumn("hit", F.lit(1)), ["a", "b"], "left")
    ok = lambda t: F.col("s") >= t if rising else F.col("s") <= t
    wide = marked.agg(*(F.count_if(ok(t)).alias(f"n{t}") for t in thresholds), *(F.count_if(ok(t) & F.col("hit").isNotNull()).alias(f"k{t}") for t in thresholds))
    wide = wide.crossJoin(truth.select("a", "b").distinct().agg(F.count(F.lit(1)).alias("positives")))  # one row each
    out = wide.select("positives", F.explode(F.array(*(F.struct(F.lit(t).alias("threshold"), F.col(f"n{t}").alias("found"), F.col(f"k{t}").alias("correct")) for t in thresholds))).alias("x"))
    return out.select("x.threshold", "x.found", "x.correct", F.round(F.try_divide("x.correct", "x.found"), 6).alias("precision"), F.round(F.try_divide("x.correct", "positives"), 6).alias("recall"))


def pair_pr_counted(found: DataFrame, truth: DataFrame, thresholds: list[int], rising: bool = True) -> DataFrame:
    """The same from found(s, n), the number of all pairs by s, and truth(s, n), that of true pairs; s is null for those that have none."""
    ok = lambda t: F.col("s") >= t if rising else F.col("s") <= t
    n = found.agg(*(F.coalesce(F.sum(F.when(ok(t), F.col("n"))), F.lit(0)).alias(f"n{t}") for t in thresholds))
    k = truth.agg(*(F.coalesce(F.sum(F.when(ok(t), F.col("n"))), F.lit(0)).alias(f"k{t}") for t in thresholds), F.coalesce(F.sum("n"), F.lit(0)).alias("positives"))
    wide = n.crossJoin(k)  # one row each
    out = wide.select("positives", F.explode(F.array(*(F.struct(F.lit(t).alias("threshold"), F.col(f"n{t}").alias("found"), F.col(f"k{t}").alias("correct")) for t in thresholds))).alias("x"))
    return out.select("x.threshold", "x.found", "x.correct", F.round(F.try_divide("x.correct", "x.found"), 6).alias("precision"), F.round(F.try_divide("x.correct", "positives"), 6).alias("recall"))


def distortion(df: DataFrame, model: CodeModel) -> DataFrame:
    """(n, total, mean) of the squared reconstruction error in the prepared space."""
    raw = len(model.mean) if model.mean is not None else model.pca.shape[0] if model.pca is not None else model.d

    def run(batches):
        for batch in batches:
            if batch.num_rows:
                x = matrix(batch, 1, raw)
                c, f = model.encode(x)
                e = ((model.prepare(x) - model.decode(c, f)) ** 2).sum(1)
                yield pa.RecordBatch.from_pydict({"n": [len(e)], "e": [float(e.sum())]})

    return usable(df).mapInArrow(run, "n long, e double").agg(F.sum("n").alias("n"), F.sum("e").alias("total")).withColumn("mean", F.col("total") / F.col("n"))


def code_bytes(model: CodeModel) -> dict[str, float]:
    """Bytes of a vector's fine codes, and bits of its coarse codes."""
    return {"fine_bytes": model.m * np.log2(max(model.k, 2)) / 8, "coarse_bits": model.halves * np.log2(max(model.K, 2))}


def probe_stats(visited: DataFrame) -> DataFrame:
    """(queries, mean_cells, mean_candidates, most_cells) of visited cells."""
    per = visited.groupBy("qid").agg(F.count(F.lit(1)).alias("w"), F.sum("n").alias("t"))
    return per.agg(F.count(F.lit(1)).alias("queries"), F.round(F.avg("w"), 6).alias("mean_cells"), F.round(F.avg("t"), 6).alias("mean_candidates"), F.max("w").alias("most_cells"))


def graph_stats(found: DataFrame, bands: tuple[int, ...] = (1, 5, 100, 10_000)) -> DataFrame:
    """(band, components, items): components by size; a band is named by its least size."""
    sizes = found.groupBy("component").agg(F.count(F.lit(1)).alias("n"))
    band = F.lit(bands[0])
    for b in bands[1:]:
        band = F.when(F.col("n") >= b, F.lit(b)).otherwise(band) if b == bands[1] else F.when(F.col("n") >= b, F.lit(b)).otherwise(band)
    return sizes.withColumn("band", band).groupBy("band").agg(F.count(F.lit(1)).alias("components"), F.sum("n").alias("items"))


def rank_corr(scored: DataFrame) -> DataFrame:
    """(qid, corr): rank agreement of score and distance d within each query."""
    r = lambda c: F.percent_rank().over(Window.partitionBy("qid").orderBy(c))
    return scored.withColumn("x", r("score")).withColumn("y", r("d")).groupBy("qid").agg(F.round(F.corr("x", "y"), 6).alias("corr"))


def orthogonality(rot: np.ndarray) -> float:
    """Largest entry of |R'R - I| over all rotations."""
    r = rot.reshape(-1, *rot.shape[-2:])
    return float(np.abs(np.einsum("kij,kil->kjl", r, r) - np.eye(r.shape[-1])).max())


def balance_ratio(variance: np.ndarray, perm: np.ndarray) -> float:
    """Product of the variances of the first half over that of the second, as a power 1/d."""
    v = np.log(np.maximum(np.asarray(variance)[perm], 1e-300))
    h = len(v) // 2
    return float(np.exp((v[:h].sum() - v[h:].sum()) / len(v)))


def timed(run) -> tuple[object, float]:
    began = time.perf_counter()
    out = run()
    return out, time.perf_counter() - began
