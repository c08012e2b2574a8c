"""Conflict-constrained best-fit packing.

Documents fill bins of a fixed number of words. A bin takes at most one document of a source
and one of a duplicate cluster; it carries both as bitmaps. Bins are kept in the order of
their residual room; for each piece, longest first, the search starts at the smallest
residual that holds it and goes on to the successors until a compatible bin is found, the
tightest one. Without any, a bin is opened.

Rows are dealt to shards by hash, of about SHARD_ROWS each, so sources and clusters of any
size spread evenly and no task grows with the input. Texts are not moved.
"""

from __future__ import annotations

from bisect import bisect_left, insort

import pandas as pd
from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

from codematch.llm.joins import each_copy
from codematch.sources.io import materialize

CAPACITY = 2048
SHARD_ROWS = 5000


def best_fit(sizes: list[int], sources: list, clusters: list, capacity: int) -> list[int]:
    """Bin numbers of pieces in the order given; None as source or cluster conflicts with nothing."""
    number: dict[str, dict] = {"s": {}, "c": {}}

    def mask(kind, value):
        if value is None:
            return 0
        known = number[kind]
        return 1 << known.setdefault(value, len(known))

    repeated = {c for c, n in pd.Series(clusters, dtype=object).value_counts().items() if n > 1}
    order: list[tuple[int, int]] = []  # residual, bin
    has_source: list[int] = []
    has_cluster: list[int] = []
    out = []
    for size, source, cluster in zip(sizes, sources, clusters, strict=True):
        s, c = mask("s", source), mask("c", cluster) if cluster in repeated else 0
        i = bisect_left(order, (size, -1))
        while i < len(order) and (has_source[order[i][1]] & s or has_cluster[order[i][1]] & c):
            i += 1
        if i < len(order):
            room, b = order.pop(i)
            has_source[b] |= s
            has_cluster[b] |= c
        else:
            room, b = capacity, len(has_source)
            has_source.append(s)
            has_cluster.append(c)
        if room > size:
            insort(order, (room - size, b))
        out.append(b)
    return out


def _pack_shard(capacity: int):
    def run(rows: pd.DataFrame) -> pd.DataFrame:
        rows = rows.sort_values(["length", "doc_id", "cluster", "piece"], ascending=[False, True, True, True], kind="stable", na_position="first")
        opt = lambda c: [None if pd.isna(x) else x for x in rows[c]]
        rows["bin_id"] = [(int(s) << 32) + b for s, b in zip(rows.shard, best_fit(rows.length.tolist(), opt("source"), opt("cluster"), capacity), strict=True)]
        return rows[["doc_id", "piece", "first_word", "length", "source", "cluster", "bin_id"]]

    return run


def pack(docs: DataFrame, capacity: int = CAPACITY, cluster: Column | None = None, shard_rows: int = SHARD_ROWS, copies_at_once: int = 100_000) -> DataFrame:
    """Pieces of the rows of docs(doc_id BIGINT, text, source): doc_id, piece, first_word, length, source, cluster, bin_id.

    The length of a document is its number of words and one for its end. A longer one than
    the capacity is cut into pieces that fill a bin each, and a rest. cluster is a column of
    docs; by default the hash of the lower-cased text with single spaces. Empty and null
    texts have length 1 and conflict with no cluster; a null source conflicts with no source.
    Repeated rows are packed each, in different bins. Other columns are ignored.
    """
    text = F.trim(F.regexp_replace(F.lower(F.coalesce(F.col("text").cast("string"), F.lit(""))), r"\s+", " "))
    words = F.when(text == "", F.lit(0)).otherwise(F.length(text) - F.length(F.replace(text, F.lit(" "), F.lit(""))) + 1)
    own = F.when(text != "", F.xxhash64(text)) if cluster is None else cluster.cast("long")
    light = docs.select(
        F.col("doc_id").cast("long").alias("doc_id"), (words + 1).cast("long").alias("total"), F.col("source").cast("string").alias("source"), own.alias("cluster")
    )
    # one pass over the texts; equal rows are counted before they are dealt
    light = materialize(light.groupBy("doc_id", "total", "source", "cluster").agg(F.count(F.lit(1)).alias("copies")), "lengths")
    n = light.agg(F.sum("copies").alias("n")).first().n or 0
    shards = max(1, -(-n // shard_rows))
    light = each_copy(light, "copies", copies_at_once)
    light = light.withColumn("shard", F.pmod(F.xxhash64("doc_id", "cluster", "copy"), F.lit(shards)).cast("long"))
    full = F.ceil(F.col("total") / capacity).cast("int")
    pieces = light.withColumn("piece", F.explode(F.sequence(F.lit(0), full - 1))).withColumn("first_word", F.col("piece").cast("long") * capacity)
    pieces = pieces.withColumn("length", F.least(F.lit(capacity).cast("long"), F.col("total") - F.col("first_word")))
    kind = "doc_id long, piece int, first_word long, length long, source string, cluster long, bin_id long"
    # a full piece has a bin of its own: named by its row, below 0
    own_bin = F.expr("CAST(-1 AS BIGINT) - pmod(xxhash64(doc_id, cluster, source, copy, piece), 4611686018427387904L)")
    whole = pieces.where(F.col("length") == capacity).withColumn("bin_id", own_bin)
    rest = pieces.where(F.col("length") < capacity).select("doc_id", "piece", "first_word", "length", "source", "cluster", "shard")
    packed = rest.groupBy("shard").applyInPandas(_pack_shard(capacity), kind)
    return whole.select("doc_id", "piece", "first_word", "length", "source", "cluster", "bin_id").unionAll(packed)
