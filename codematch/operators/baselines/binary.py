"""Binary codes: words of 32 bits in ARRAY<BIGINT>, and Hamming search over them."""

from __future__ import annotations

from collections.abc import Callable
from functools import reduce

import numpy as np
import pyarrow as pa
from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

from codematch.operators.encode import matrix, usable
from codematch.operators.search import small, top

WORD = 32


def pack(bits: np.ndarray) -> np.ndarray:
    """(n, bits) of 0 / 1 -> (n, words); bit i of a word has value 2**i."""
    n, b = bits.shape
    wide = np.zeros((n, -(-b // WORD) * WORD), np.int64)
    wide[:, :b] = bits
    return (wide.reshape(n, -1, WORD) << np.arange(WORD)).sum(2)


def encode(df: DataFrame, d: int, bits_of: Callable[[np.ndarray], np.ndarray]) -> DataFrame:
    """(id, words) by a function of a matrix of vectors."""

    def run(batches):
        for batch in batches:
            if batch.num_rows:
                yield pa.RecordBatch.from_arrays([batch.column(0), pa.array(list(pack(bits_of(matrix(batch, 1, d)))), pa.list_(pa.int64()))], names=["id", "words"])

    return usable(df).mapInArrow(run, "id long, words array<long>")


def hamming(a: Column, b: Column, words: int) -> Column:
    return reduce(lambda x, y: x + y, (F.bit_count(F.get(a, F.lit(i)).bitwiseXOR(F.get(b, F.lit(i)))) for i in range(words)), F.lit(0))


def hamming_scan(q: DataFrame, x: DataFrame, words: int) -> DataFrame:
    """(qid, id, score = distance): a stated query set against all rows."""
    q = q.select(F.col("id").alias("qid"), F.col("words").alias("qw"))
    return small(q).crossJoin(x).where("qid <> id").select("qid", "id", hamming(F.col("qw"), F.col("words"), words).cast("double").alias("score"))


def hamming_knn(q: DataFrame, x: DataFrame, R: int, words: int) -> DataFrame:
    return top(hamming_scan(q, x, words), R, rising=True)


def band_columns(bits: int, bands: int) -> list[Column]:
    """The bands of a code as BIGINT columns: band b has bits [b * bits / bands, (b + 1) * bits / bands)."""
    out = []
    for b in range(bands):
        lo, hi = b * bits // bands, (b + 1) * bits // bands
        parts, i = [], lo
        while i < hi:
            word, at = divmod(i, WORD)
            n = min(hi - i, WORD - at)
            parts.append(F.shiftright(F.get("words", F.lit(word)), at).bitwiseAND(F.lit((1 << n) - 1)))
            i += n
        out.append(parts[0] if len(parts) == 1 else F.xxhash64(*parts))
    return out


def banded_pairs(codes: DataFrame, bits: int, bands: int) -> DataFrame:
    """(a, b) of codes that are equal in a band: an equi-join of band values."""
    rows = codes.select("id", F.posexplode(F.array(*band_columns(bits, bands))).alias("band", "value"))
    x, y = rows.select(F.col("id").alias("a"), "band", "value"), rows.select(F.col("id").alias("b"), "band", "value")
    return x.join(y, ["band", "value"]).where("a < b").select("a", "b").distinct()


def hamming_pairs(codes: DataFrame, radius: int, bits: int) -> DataFrame:
    """(a, b, dist) of all pairs within the radius: of radius + 1 bands one is equal (pigeonhole), and candidates are checked."""
    words = -(-bits // WORD)
    met = banded_pairs(codes, bits, min(radius + 1, bits))
    both = met.join(codes.select(F.col("id").alias("a"), F.col("words").alias("x")), "a").join(codes.select(F.col("id").alias("b"), F.col("words").alias("y")), "b")
    return both.select("a", "b", hamming(F.col("x"), F.col("y"), words).alias("dist")).where(F.col("dist") <= radius)


def recall_by_radius(q: DataFrame, x: DataFrame, truth: DataFrame, radii: list[int], words: int) -> DataFrame:
    """(radius, mean_found, recall): unordered retrieval, grown by the radius; mean_found is the R of a recall@R curve."""
    scan = hamming_scan(q, x, words).join(truth.select("qid", "id").withColumn("hit", F.lit(1)), ["qid", "id"], "left")
    wide = scan.agg(F.countDistinct("qid").alias("q"), *(F.count_if(F.col("score") <= r).alias(f"n{r}") for r in radii), *(F.count_if((F.col("score") <= r) & F.col("hit").isNotNull()).alias(f"k{r}") for r in radii))
    return wide.select("q", F.explode(F.array(*(F.struct(F.lit(r).alias("radius"), F.col(f"n{r}").alias("n"), F.col(f"k{r}").alias("k")) for r in radii))).alias("x")).select("x.radius", F.round(F.col("x.n") / F.col("q"), 6).alias("mean_found"), F.round(F.col("x.k") / F.col("q"), 6).alias("recall"))
