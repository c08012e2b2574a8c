"""Quality by a Gaussian kernel over document statistics.

The kernel is approximated by random Fourier features; ridge weights come from normal
equations that partitions sum up; isotonic regression turns the ridge scores into
probabilities. Statistics are computed once for each document, over its whole text, and all
else reads them.
"""

from __future__ import annotations

from collections import Counter

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from codematch.sources.io import materialize

FEATURES, RIDGE, SEED = 256, 1e-4, 5
#: Ridge scores are counted in this many bins for the isotonic fit.
BINS = 1000
NAMES = ("log_bytes", "log_words", "word_length", "longest_word", "upper_words", "odd_words", "distinct_words", "top_word", "same_as_before", "distinct_pairs", "log_lines", "repeated_lines", "line_length", "letters", "upper", "digits", "marks", "symbols", "bars", "exclamations", "spaces", "top_share_pair")
_SYMBOLS, _MARKS = b"#$%&*@^~<>={}[]\\_+/", b".,;:?\"'()-"


def statistics(text: bytes | None) -> list[float]:
    """Numbers that describe a UTF-8 text; all 0 for an empty one."""
    if not text or not (words := text.split()):
        return [0.0] * len(NAMES)
    n, k = len(text), len(words)
    by = np.bincount(np.frombuffer(text, np.uint8), minlength=256)
    upper = by[65:91].sum()
    letters = upper + by[97:123].sum() + by[128:].sum()
    count = Counter(words)
    pairs = Counter(zip(words, words[1:], strict=False))
    lines = text.split(b"\n")
    lengths = np.fromiter(map(len, words), np.int64, k)
    few = lambda bag: float(by[list(bag)].sum())
    return [
        np.log1p(n), np.log1p(k), float(lengths.mean()), float(np.log1p(lengths.max())), sum(map(bytes.isupper, words)) / k, sum(not w[-1:].isalpha() and w[-1:] not in b".,;:?!" and w[-1] < 128 for w in words) / k,
        len(count) / k, max(count.values()) / k, sum(a == b for a, b in zip(words, words[1:], strict=False)) / k, len(pairs) / max(k - 1, 1), np.log1p(len(lines)), 1 - len(set(lines)) / len(lines), float(np.log1p(n / len(lines))),
        float(letters / n), float(upper / n), float(by[48:58].sum() / n), few(_MARKS) / n, few(_SYMBOLS) / n, by[124] / n, by[33] / n, by[32] / n, max(pairs.values(), default=0) / max(k - 1, 1),
    ]


def _describe(batches):
    for batch in batches:
        for at in range(0, batch.num_rows, 256):
            part = batch.slice(at, 256)
            out = [statistics(t) for t in part.column(1).cast(pa.binary()).to_pylist()]
            yield pa.RecordBatch.from_arrays([part.column(0), pa.array(out, pa.list_(pa.float64()))], names=["doc_id", "stats"])


class FourierFeatures:
    """cos(x W + b) over standardized statistics, and a constant: inner products approach a Gaussian kernel of the given width."""

    def __init__(self, mean: np.ndarray, deviation: np.ndarray, n: int = FEATURES, seed: int = SEED, width: float | None = None):
        rng = np.random.default_rng(seed)
        d = len(mean)
        self.mean, self.deviation = mean, np.where(deviation > 1e-9, deviation, 1.0)
        self.weights, self.shift = rng.normal(0, 1 / (width or np.sqrt(d)), (d, n)), rng.uniform(0, 2 * np.pi, n)

    def __call__(self, stats: np.ndarray) -> np.ndarray:
        x = np.clip((stats - self.mean) / self.deviation, -6, 6)
        return np.c_[np.cos(x @ self.weights + self.shift) * np.sqrt(2 / len(self.shift)), np.ones(len(x))]


def _matrix(batch: pa.RecordBatch, column: int) -> np.ndarray:
    return np.array(batch.column(column).to_pylist(), float).reshape(batch.num_rows, len(NAMES))


def summed(rows: DataFrame, partial, groups: int = 16) -> np.ndarray:
    """Sum over partitions of the float64 array that partial(batch) returns: partial sums first, then `groups` tasks, then the driver."""

    def first(batches):
        total = None
        for batch in batches:
            if batch.num_rows:
                x = partial(batch)
                total = x if total is None else total + x
        if total is not None:
            yield pa.RecordBatch.from_pydict({"part": [total.tobytes()]})

    def second(batches):
        total = None
        for batch in batches:
            for x in batch.column(0).to_pylist():
                y = np.frombuffer(x)
                total = y.copy() if total is None else total + y
        if total is not None:
            yield pa.RecordBatch.from_pydict({"part": [total.tobytes()]})

    parts = rows.mapInArrow(first, "part binary").repartition(groups).mapInArrow(second, "part binary").collect()
    return np.sum([np.frombuffer(bytes(p.part)) for p in parts], axis=0) if parts else np.zeros(0)


def isotonic(x: np.ndarray, y: np.ndarray, weight: np.ndarray) -> tuple[np.ndarray, np.ndarray]:
    """The rising step function closest to y, by pooling neighbours that fall: (centres, values) for interpolation."""
    blocks: list[list[float]] = []  # weight, sum of y, sum of x
    for a, b, w in zip(x, y, weight, strict=True):
        blocks.append([w, b * w, a * w])
        while len(blocks) > 1 and blocks[-2][1] * blocks[-1][0] >= blocks[-1][1] * blocks[-2][0]:
            last = blocks.pop()
            blocks[-1] = [p + q for p, q in zip(blocks[-1], last, strict=True)]
    return np.array([b[2] / b[0] for b in blocks]), np.array([b[1] / b[0] for b in blocks])


def held_out(doc_id):
    return F.crc32(doc_id.cast("string")) % 5 == 0


def score_documents(docs: DataFrame, labels: DataFrame, threshold: float = 0.3) -> DataFrame:
    """One row per row of docs(doc_id BIGINT, text): doc_id, held_out, score, predicted.

    Learns from all labels(doc_id, quality) of rows that are not held out: the ridge from
    four fifths of them, the calibration from the rest. Without labels every score is 0.5.
    Null and empty texts are scored from statistics of 0. A row without doc_id is scored and
    not held out. Repeated rows get a row each; of several labels of an id the largest
    counts. Other columns are ignored.
    """
    described = materialize(docs.select(F.col("doc_id").cast("long").alias("doc_id"), F.col("text").cast("string").alias("text")).mapInArrow(_describe, "doc_id long, stats array<double>"), "statistics")
    known = labels.where(F.col("doc_id").isNotNull() & F.col("quality").isNotNull() & ~held_out(F.col("doc_id"))).groupBy(F.col("doc_id").alias("labelled_id")).agg(F.max("quality").cast("double").alias("label"))
    rows = described.join(known, F.col("doc_id") == F.col("labelled_id")).select("doc_id", "stats", "label")
    calibrates = F.pmod(F.xxhash64(F.col("doc_id"), F.lit("calibrate")), F.lit(5)) == 0
    rows = materialize(rows.withColumn("calibrates", calibrates), "labelled")
    fitted = rows.where(~F.col("calibrates")).select("stats", "label")

    def moments(batch):
        x = _matrix(batch, 0)
        return np.r_[len(x), x.sum(0), (x * x).sum(0)]

    m = summed(fitted, moments)
    if not len(m):
        out = described.select("doc_id", F.lit(0.5).alias("score"))
    else:
        d = len(NAMES)
        mean = m[1 : d + 1] / m[0]
        lift = FourierFeatures(mean, np.sqrt(np.maximum(m[d + 1 :] / m[0] - mean**2, 0)))

        def normal(batch):
            z, y = lift(_matrix(batch, 0)), batch.column(1).to_numpy(zero_copy_only=False)
            return np.r_[(z.T @ z).ravel(), z.T @ y]

        size = FEATURES + 1
        total = summed(fitted, normal)
        gram, right = total[: size * size].reshape(size, size), total[size * size :]
        weights = np.linalg.solve(gram + RIDGE * m[0] * np.eye(size), right)

        def ridge(batches):
            for batch in batches:
                if batch.num_rows:
                    yield pa.RecordBatch.from_arrays([batch.column(0), pa.array(lift(_matrix(batch, 1)) @ weights)], names=["doc_id", "raw"])

        def ridge_labelled(batches):
            for batch in batches:
                if batch.num_rows:
                    yield pa.RecordBatch.from_arrays([batch.column(0), pa.array(lift(_matrix(batch, 1)) @ weights)], names=["label", "raw"])

        place = F.floor(F.least(F.greatest("raw", F.lit(-0.5)), F.lit(1.5)) * (BINS / 2))
        kept = rows.where("calibrates").select("label", "stats").mapInArrow(ridge_labelled, "label double, raw double")
        bins = sorted(tuple(r) for r in kept.groupBy(place.alias("bin")).agg(F.avg("raw"), F.avg("label"), F.count(F.lit(1)).cast("double")).collect())
        if len(bins) > 1:
            centres, values = isotonic(*(np.array([b[i] for b in bins]) for i in (1, 2, 3)))
        else:
            centres, values = np.array([0.0, 1.0]), np.array([0.0, 1.0])

        def calibrated(batches):
            for batch in ridge(batches):
                yield pa.RecordBatch.from_arrays([batch.column(0), pa.array(np.clip(np.interp(batch.column(1).to_numpy(), centres, values), 0, 1))], names=["doc_id", "score"])

        out = described.mapInArrow(calibrated, "doc_id long, score double")
    return out.select("doc_id", F.coalesce(held_out(F.col("doc_id")), F.lit(False)).alias("held_out"), "score", (F.col("score") >= threshold).cast("int").alias("predicted"))
