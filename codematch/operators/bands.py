"""Pairs of rows whose values are near: a band join of a table with itself."""

from __future__ import annotations

from pyspark.sql import DataFrame
from pyspark.sql import functions as F

#: Keys of one value in a list, on average; bins of a width.
LIST, BINS = 1024, 8


def band_pairs(rows: DataFrame, key: str, value: str, width: float, most: int = LIST) -> DataFrame:
    """(a, b), a < b, for rows whose values are `width` or less apart, as double arithmetic has it; width is a power of two.

    Keys of one value are dealt by hash over lists of about `most`. Lists meet on bins of values, each
    two of them once, so a meeting of two lists is one row; it is dealt anew before its pairs are made.
    A rounded difference can hide one bin more than the width has.
    """
    spark = rows.sparkSession
    own = rows.select(F.col(key).alias("key"), F.col(value).cast("double").alias("v")).where("key IS NOT NULL AND v IS NOT NULL")
    many = own.groupBy("v").agg(F.ceil(F.count(F.lit(1)) / most).cast("int").alias("lists")).where("lists > 1")
    dealt = own.join(many, "v", "left").withColumn("list", F.pmod(F.xxhash64("key"), F.coalesce("lists", F.lit(1))).cast("int"))
    lists = dealt.groupBy("v", "list").agg(F.collect_list("key").alias("keys")).withColumn("bin", F.floor(F.col("v") * (BINS / width)))
    x = lists.select("bin", *(F.col(c).alias(f"{c}_x") for c in ("v", "list", "keys")))
    y = lists.select(F.explode(F.transform(F.sequence(F.lit(0), F.lit(BINS + 1)), lambda i: F.col("bin") - i)).alias("bin"), *(F.col(c).alias(f"{c}_y") for c in ("v", "list", "keys")))
    once = f"(v_x < v_y OR v_x = v_y AND list_x <= list_y) AND abs(v_x - v_y) <= {width!r}D"
    met = x.join(y, "bin").where(once).select("keys_x", "keys_y", F.expr("v_x = v_y AND list_x = list_y").alias("same"))
    met = met.repartition(int(spark.conf.get("spark.sql.shuffle.partitions")))
    pairs = met.select(F.explode("keys_x").alias("x"), "keys_y", "same").select("x", F.explode("keys_y").alias("y"), "same")
    return pairs.where("x < y OR x > y AND NOT same").select(F.least("x", "y").alias("a"), F.greatest("x", "y").alias("b"))
