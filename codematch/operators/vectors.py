"""Vector views of the given tables: (id BIGINT, vec ARRAY<DOUBLE>, grp STRING).

Numeric views are SQL that Spark and other engines read alike; the statistics that scale
them are one row, joined by broadcast. Text views are a narrow map: words are hashed and
counted where the text lies, without a shuffle.
"""

from __future__ import annotations

import hashlib

import numpy as np
import pyarrow as pa
import regex
from pyspark.sql import Column, DataFrame, SparkSession
from pyspark.sql import functions as F

from codematch.sources.io import materialize, read_table

VEC = "id long, vec array<double>, grp string"
_WORD = regex.compile(r"[\p{L}\p{N}]+")


class Buckets(dict):
    """word -> bucket: the first 8 hexadecimal digits of its md5, modulo d."""

    def __init__(self, d: int):
        super().__init__()
        self.d = d

    def __missing__(self, word: str) -> int:
        if len(self) > 300_000:
            self.clear()
        value = self[word] = int(hashlib.md5(word.encode()).hexdigest()[:8], 16) % self.d
        return value


def text_vectors(df: DataFrame, id_: Column, text: Column, grp: Column, d: int = 64) -> DataFrame:
    """Hashed word counts of a text, scaled to length 1; all 0 for a text without words."""

    def run(batches):
        buckets = Buckets(d)
        for batch in batches:
            out = []
            for t in batch.column(1).to_pylist():
                n = np.bincount([buckets[w] for w in _WORD.findall(t.lower())] if t else [], minlength=d).astype(float)
                norm = np.sqrt((n * n).sum())
                out.append((n / norm if norm else n).tolist())
            yield pa.RecordBatch.from_arrays([batch.column(0), pa.array(out, pa.list_(pa.float64())), batch.column(2)], names=["id", "vec", "grp"])

    return df.select(id_.cast("long").alias("id"), text.cast("string").alias("text"), grp.cast("string").alias("grp")).mapInArrow(run, VEC)


def embeddings(spark: SparkSession, sf: str) -> DataFrame:
    return read_table(spark, sf, "embeddings").select(F.col("vec_id").alias("id"), F.transform("embedding", lambda x: x.cast("double")).alias("vec"), F.col("label").cast("string").alias("grp"))


def documents(spark: SparkSession, sf: str) -> DataFrame:
    return text_vectors(read_table(spark, sf, "documents"), F.col("doc_id"), F.col("text"), F.col("lang"))


def shown_text(html: Column) -> Column:
    """Text of a page: scripts, styles, comments and tags become blanks."""
    for pattern in PAGE_PATTERNS:
        html = F.regexp_replace(html, pattern, " ")
    return html


PAGE_PATTERNS = (r"(?is)<script.*?</script>", r"(?is)<style.*?</style>", r"(?s)<!--.*?-->", r"<[^>]*>")
PAGE_LANGUAGE = r"<html[^>]*lang=\"([a-z]+)"


def pages(spark: SparkSession, sf: str) -> DataFrame:
    p = read_table(spark, sf, "pages")
    return text_vectors(p, F.col("page_id"), shown_text(F.col("html")), F.regexp_extract("html", PAGE_LANGUAGE, 1))


#: Turns that a conversation can have; an id is conv_id * TURNS + turn.
TURNS = 1 << 24


def turns(spark: SparkSession, sf: str) -> DataFrame:
    c = read_table(spark, sf, "conversations")
    return text_vectors(c, F.col("conv_id") * TURNS + F.col("turn"), F.col("text"), F.col("role"))


def benchmark(spark: SparkSession, sf: str) -> DataFrame:
    return text_vectors(read_table(spark, sf, "benchmark"), F.col("item_id"), F.col("text"), F.lit(None))


def _shares(column: str, values, name: str) -> list[tuple[str, str]]:
    return [(f"{name}{i}", f"avg(CASE WHEN {column} = {v} THEN 1.0E0 ELSE 0.0E0 END)") for i, v in enumerate(values)]


#: view -> (source relation, id, group, features as (name, aggregate))
NUMERIC = {
    "parts": (
        "{part} JOIN {lineitem} ON l_partkey = p_partkey", "p_partkey", "max(p_brand)",
        [("q1", "avg(l_quantity)"), ("q2", "stddev_pop(l_quantity)"), ("p1", "avg(l_extendedprice)"), ("p2", "stddev_pop(l_extendedprice)"), ("d1", "avg(l_discount)"), ("t1", "avg(l_tax)"), *_shares("l_returnflag", ["'R'", "'A'"], "r"), *_shares("l_linestatus", ["'F'"], "s"), *_shares("quarter(l_shipdate)", range(1, 5), "k"), ("z1", "max(CAST(p_size AS DOUBLE))"), ("z2", "max(p_retailprice)"), ("z3", "CAST(count(*) AS DOUBLE)")],
    ),
    "customers": (
        "{customer} JOIN {orders} ON o_custkey = c_custkey", "c_custkey", "max(c_mktsegment)",
        [*_shares("month(o_orderdate)", range(1, 13), "m"), ("t1", "avg(o_totalprice)"), ("n1", "CAST(count(*) AS DOUBLE)"), ("b1", "max(c_acctbal)"), *_shares("o_orderpriority", ["'1-URGENT'"], "u")],
    ),
    "users": (
        "{events}", "user_id", "CAST(NULL AS VARCHAR(8))",
        [*_shares("hour(ts)", range(24), "h"), *_shares("event_type", ["'click'", "'view'", "'signup'", "'purchase'", "'error'"], "e"), ("v1", "avg(value)"), ("v2", "max(value)"), ("v3", "stddev_pop(value)")],
    ),
}


def _features_sql(view: str) -> str:
    source, key, grp, features = NUMERIC[view]
    return f"SELECT {key} AS id, {grp} AS grp, {', '.join(f'{a} AS {n}' for n, a in features)} FROM {source} GROUP BY {key}"


def _scaled_sql(view: str, f: str) -> tuple[str, str]:
    """The mean and deviation of the features of the relation f in one row, and the features scaled by these, s."""
    names = [n for n, _ in NUMERIC[view][3]]
    s = ", ".join(f"avg({n}) AS a_{n}, stddev_pop({n}) AS d_{n}" for n in names)
    z = ", ".join(f"round(CASE WHEN d_{n} > 1e-12 THEN ({n} - a_{n}) / d_{n} ELSE 0.0E0 END, 6) AS z_{n}" for n in names)
    return f"SELECT {s} FROM {f}", f"SELECT id, grp, {z} FROM {f} CROSS JOIN s"


def numeric_sql(view: str) -> str:
    """The view as SQL over {table} placeholders: f has the features, s their mean and deviation in one row."""
    s, z = _scaled_sql(view, "f")
    return f"WITH f AS ({_features_sql(view)}), s AS ({s}) {z}"


def _numeric(spark: SparkSession, sf: str, view: str, stored: bool = False) -> DataFrame:
    """stored: the features are written once, and not computed again for their mean and each later pass."""
    tables = {t: read_table(spark, sf, t) for t in ("part", "lineitem", "customer", "orders", "events") if "{" + t + "}" in NUMERIC[view][0]}
    if stored:
        s, z = _scaled_sql(view, "{f}")
        rows = spark.sql(f"WITH s AS ({s}) {z}", f=materialize(spark.sql(_features_sql(view), **tables), "features"))
    else:
        rows = spark.sql(numeric_sql(view), **tables)
    return rows.select(F.col("id").cast("long").alias("id"), F.array(*(F.col(f"z_{n}").cast("double") for n, _ in NUMERIC[view][3])).alias("vec"), F.col("grp").cast("string").alias("grp"))


def parts(spark: SparkSession, sf: str, stored: bool = False) -> DataFrame:
    return _numeric(spark, sf, "parts", stored)


def customers(spark: SparkSession, sf: str) -> DataFrame:
    return _numeric(spark, sf, "customers")


def users(spark: SparkSession, sf: str) -> DataFrame:
    return _numeric(spark, sf, "users")


VIEWS = {"embeddings": embeddings, "documents": documents, "parts": parts, "customers": customers, "users": users, "pages": pages, "turns": turns, "benchmark": benchmark}
DIMENSIONS = {"embeddings": 64, "documents": 64, "parts": 16, "customers": 16, "users": 32, "pages": 64, "turns": 64, "benchmark": 64}
