"""Connected components of an edge table, by alternating star contractions."""

from __future__ import annotations

from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from codematch.sources.io import discard, materialize


def _mark(edges: DataFrame) -> tuple:
    row = edges.agg(F.count(F.lit(1)).alias("n"), F.sum(F.hash("u", "v").cast("long")).alias("s"), F.sum(F.crc32(F.concat_ws(":", "u", "v").cast("binary"))).alias("c")).first()
    return tuple(row)


def _large_star(edges: DataFrame) -> DataFrame:
    """Every larger neighbour of a node is tied to the smallest of the node and its neighbours."""
    both = edges.unionAll(edges.select(F.col("v").alias("u"), F.col("u").alias("v")))
    least = both.groupBy("u").agg(F.least(F.min("v"), F.col("u")).alias("m"))
    return both.where("v > u").join(least, "u").select(F.col("v").alias("u"), F.col("m").alias("v")).where("u <> v").distinct()


def _small_star(edges: DataFrame) -> DataFrame:
    """The smaller neighbours of a node, and the node, are tied to the smallest of them."""
    least = edges.groupBy("u").agg(F.min("v").alias("m"))
    moved = edges.join(least, "u").select(F.col("v").alias("u"), F.col("m").alias("v"))
    return moved.unionAll(least.select("u", F.col("m").alias("v"))).where("u <> v").distinct()


def star_components(edges: DataFrame, a: str = "a", b: str = "b", max_rounds: int = 60) -> DataFrame:
    """(id, component) for every node that an edge touches; component is the smallest id that it reaches.

    Edges are undirected, may repeat and may be loops; null ends are ignored. Ids must be
    comparable (BIGINT). Each round writes its edges to the shared folder, so the plan stays
    short and a lost executor costs one round at most. Nothing is collected but a count and
    two checksums a round. No edges: no rows.
    """
    kind = edges.schema[a].dataType
    loops = edges.where(F.col(a).isNotNull() & (F.col(a) == F.col(b))).select(F.col(a).alias("id")).distinct()
    now = materialize(edges.where((F.col(a) != F.col(b))).select(F.greatest(a, b).cast(kind).alias("u"), F.least(a, b).cast(kind).alias("v")).distinct(), "star")
    mark = _mark(now)
    for _ in range(max_rounds):
        if not mark[0]:
            break
        after = materialize(_small_star(_large_star(now)), "star")
        new = _mark(after)
        discard(now)
        now, same, mark = after, new == mark, new
        if same:
            break
    else:
        raise RuntimeError("components did not settle")
    tied = now.select(F.col("u").alias("id"), F.col("v").alias("component"))
    roots = now.select(F.col("v").alias("id")).distinct().withColumn("component", F.col("id"))
    found = tied.unionAll(roots)
    return found.unionAll(loops.join(found, "id", "left_anti").withColumn("component", F.col("id")))
