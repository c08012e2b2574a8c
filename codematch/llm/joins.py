"""Joins with a table of one row a key, whatever share of the rows a key has."""

from __future__ import annotations

from functools import reduce

from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

#: Broadcast a table only up to so many rows; of a larger one, only keys with one in HEAVY rows or more.
MOST, HEAVY = 200_000, 10_000


def _match(on: dict[str, str]) -> Column:
    return reduce(Column.__and__, (F.col(a).eqNullSafe(F.col(b)) for a, b in on.items()))


def left_join(
    rows: DataFrame, table: DataFrame, on: dict[str, str], size: str | None = None, found: str | None = None, most: int = MOST, heavy: int = HEAVY
) -> DataFrame:
    """rows with the columns of table but its keys and `size`; on: column of rows -> column of table, which other tables don't have.

    Null keys match null keys. table has a row a key; size is a column of it, the number of
    rows with this key, and found one that is never null. A table of more than `most` rows is
    joined by shuffle, but for the keys with one in `heavy` of all rows or more, of which there
    are no more than `heavy`: they are broadcast, and their rows stay where they are. Both
    sides should be tables that were written, as they are read up to three times.
    """
    gone = [*on.values(), *([size] if size else [])]
    if table.limit(most + 1).count() <= most:
        return rows.join(F.broadcast(table), _match(on), "left").drop(*gone)
    if size is None:
        return rows.join(table, _match(on), "left").drop(*gone)
    least = (table.agg(F.sum(size).alias("n")).first().n or 0) / heavy
    added = [c for c in table.columns if c not in gone]
    first = rows.join(F.broadcast(table.where(F.col(size) >= least)), _match(on), "left").drop(*gone)
    rest = first.where(F.col(found).isNull()).drop(*added)
    light = rest.join(table.where(F.col(size) < least), _match(on), "left").drop(*gone)
    return first.where(F.col(found).isNotNull()).unionByName(light)


def each_copy(rows: DataFrame, copies: str, block: int = 100_000) -> DataFrame:
    """rows with `copy` from 1 to the number in column `copies`, a row for each; a row with more than `block` is first dealt in blocks over the tasks."""
    first, last = F.lit(1).cast("long"), F.col(copies).cast("long")
    if rows.where(F.col(copies) > block).limit(1).count():
        n = int(rows.sparkSession.conf.get("spark.sql.shuffle.partitions"))
        at = F.explode(F.sequence(F.lit(0).cast("long"), F.floor((last - 1) / block).cast("long")))
        rows = rows.withColumn("at_block", at).repartition(n, "at_block", *(c for c in rows.columns))
        first, last = F.col("at_block") * block + 1, F.least(last, (F.col("at_block") + 1) * block)
    return rows.withColumn("copy", F.explode(F.sequence(first, last))).drop("at_block")
