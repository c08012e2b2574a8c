"""Search by tags: rows that have all terms, by how often they have them."""

from __future__ import annotations

from functools import reduce

from pyspark.sql import DataFrame, Window
from pyspark.sql import functions as F


def _occurrences(term: str):
    return F.size(F.filter("words", lambda w: w == term))


def search(docs: DataFrame, terms: list[str], P: int) -> DataFrame:
    """(id, score, rnk) of docs(id, text): all terms present as words, most occurrences first, ties by id."""
    words = F.filter(F.split(F.lower("text"), r"[^\p{L}\p{N}]+"), lambda w: w != "")
    n = [_occurrences(t) for t in terms]
    scored = docs.select("id", words.alias("words")).where(reduce(lambda a, b: a & b, (F.array_contains("words", t) for t in terms))).select("id", reduce(lambda a, b: a + b, n).cast("long").alias("score"))
    best = scored.orderBy(F.desc("score"), "id").limit(P)
    return best.withColumn("rnk", F.row_number().over(Window.orderBy(F.desc("score"), "id")))  # P rows
