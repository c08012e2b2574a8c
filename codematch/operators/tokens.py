"""Tokens: (coarse code, position, fine code) packed in one BIGINT."""

from __future__ import annotations

from pyspark.sql import DataFrame
from pyspark.sql import functions as F


def flatten(codes: DataFrame, keep: tuple[str, ...] = ("id",), span: int = 1) -> DataFrame:
    """(keep..., token), one row per position. token = coarse << 32 | position << 16 | fine.

    Positions of the first half carry c1, the others c2; without c2 all carry c1. span > 1
    makes compound tokens of that many consecutive positions, by hash: fewer matches each.
    """
    m = F.size("fine")
    coarse = F.when(F.col("c2").isNull() | (F.col("pos") < F.floor(m / 2)), F.col("c1")).otherwise(F.col("c2"))
    rows = codes.select(*keep, "c1", "c2", "fine", F.posexplode("fine").alias("pos", "f"))
    packed = F.shiftleft(coarse.cast("long"), 32).bitwiseOR(F.shiftleft(F.col("pos").cast("long"), 16)).bitwiseOR(F.col("f").cast("long"))
    if span == 1:
        return rows.select(*keep, packed.alias("token"))
    rows = rows.where(F.col("pos") + span <= m)
    return rows.select(*keep, F.xxhash64("c1", "c2", "pos", F.slice("fine", F.col("pos") + 1, F.lit(span))).alias("token"))


def frequencies(tokens: DataFrame) -> DataFrame:
    """(token, n): in how many items a token is."""
    return tokens.groupBy("token").agg(F.countDistinct("id").alias("n"))


def stoplist(tokens: DataFrame, lo: int = 10, hi: int = 10_000, broadcast_up_to: int = 500_000) -> DataFrame:
    """Tokens whose number of items is within [lo, hi]; both bounds are lossy unless lo <= 2 and hi holds all."""
    bad = frequencies(tokens).where((F.col("n") < lo) | (F.col("n") > hi)).select("token")
    return tokens.join(F.broadcast(bad) if bad.limit(broadcast_up_to + 1).count() <= broadcast_up_to else bad, "token", "left_anti").select(*tokens.columns)


def stoplist_quantiles(tokens: DataFrame, lo_q: float, hi_q: float) -> DataFrame:
    """The same with bounds that are quantiles of the frequencies: the least one that this share of the tokens doesn't exceed.

    Exact; an aggregate holds the different frequencies, which are few: n of them take n * n / 2 rows.
    """
    at = lambda q: F.expr(f"percentile_disc({q}D) WITHIN GROUP (ORDER BY n)")
    lo, hi = frequencies(tokens).agg(at(lo_q), at(hi_q)).first()
    return tokens if lo is None else stoplist(tokens, int(lo), int(hi))


def fanout(tokens: DataFrame) -> DataFrame:
    """(tokens, rows, pairs, largest): what a self-join by token will make."""
    n = F.col("n")
    return frequencies(tokens).agg(F.count(F.lit(1)).alias("tokens"), F.sum(n).alias("rows"), F.sum(F.expr("n * (n - 1) DIV 2")).alias("pairs"), F.max(n).alias("largest"))
