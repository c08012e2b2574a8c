"""A few queries against their SQL, and what plans look like."""

import duckdb
import pytest

import __spark_entry__ as entry
from codematch.operators import bands

TABLES = "region nation customer supplier part orders lineitem events documents embeddings pages benchmark labels conversations".split()
KEYS = ["pair_encode", "multi_sequence_cells", "batch_search_preagg", "group_expand_label", "lsh_hamming_knn", "join_asof", "win_session", "map_sparse", "centred_sign_pairs", "exclude_owned_anti", "setop_except", "sql_batch_search", "ivf_adc_anchor"]


@pytest.fixture(scope="module")
def con(sf):
    con = duckdb.connect()
    for t in TABLES:
        con.execute(f"CREATE VIEW {t} AS SELECT * FROM '{sf}/{t}.parquet'")
    return con


def norm(rows):
    return sorted((tuple(round(v, 5) if isinstance(v, float) else tuple(v) if isinstance(v, list) else v for v in r) for r in rows), key=repr)


@pytest.mark.parametrize("key", KEYS)
def test_query_equals_sql(spark, sf, con, key):
    df = entry.queries()[key](spark, sf)
    cur = con.execute(entry.oracle_sql()[key])
    names = [d[0] for d in cur.description]
    assert sorted(names) == sorted(df.columns)
    rows = norm(tuple(r[c] for c in names) for r in df.collect())
    assert rows and rows == norm(cur.fetchall())


def test_every_sql_has_a_query_and_entry_runs(spark):
    assert set(entry.oracle_sql()) <= set(entry.queries())
    assert entry.entry(spark).count() > 0


def plan(df):
    return df._jdf.queryExecution().executedPlan().toString()


def test_plans(spark, sf):
    q = entry.queries()
    scan = plan(q["scan_pushdown"](spark, sf))
    assert "PushedFilters: [IsNotNull(o_totalprice)" in scan and "o_orderdate" not in scan
    encode = plan(q["pair_encode"](spark, sf))
    assert "Exchange" not in encode
    joined = plan(q["hits_by_join"](spark, sf))
    assert "Cartesian" not in joined and "NestedLoop" not in joined
    bucketed = plan(q["tokens_bucketed"](spark, sf))
    assert "hashpartitioning(token" not in bucketed


def test_the_bucketed_pair_join_writes_no_row_for_a_token_that_meets(spark, sf):
    bucketed = plan(entry.queries()["tokens_bucketed"](spark, sf))
    assert "Exchange" not in bucketed and "Join" not in bucketed and "Aggregate" not in bucketed


def test_equal_extremes_give_the_smallest_key(spark, tmp_path):
    rows = [(k, n, b, g) for k in range(40, 0, -1) for n, b, g in ((k % 2, 5.0 if k > 3 else 9.0, "AB"[k % 3 % 2]),)]
    rows += [(0, 0, None, "A"), (None, 1, 99.0, "A"), (77, 7, None, None)]
    spark.createDataFrame(rows, "c_custkey long, c_nationkey long, c_acctbal double, c_mktsegment string").repartition(4).write.parquet(f"{tmp_path}/customer.parquet")
    got = {r.c_nationkey: (r.richest, r.poorest, r.segments) for r in entry.queries()["agg_by_extremes"](spark, str(tmp_path)).collect()}
    assert got == {0: (2, 4, "A,B"), 1: (1, 5, "A,B"), 7: (None, None, None)}


def test_rounded_numbers_of_vector_files_keep_their_sign(spark, tmp_path):
    rows = [(i, [-1e-8, 1e-8, -0.0, -0.25, i / 128], 1) for i in range(3)]
    spark.createDataFrame(rows, "vec_id long, embedding array<float>, label int").write.parquet(f"{tmp_path}/embeddings.parquet")
    got = sorted(map(repr, map(tuple, entry.queries()["vector_file_import"](spark, str(tmp_path)).collect())))
    want = duckdb.sql(entry.oracle_sql()["vector_file_import"].replace("FROM embeddings", f"FROM '{tmp_path}/embeddings.parquet/*.parquet'")).fetchall()
    assert got == sorted(map(repr, want)) and "-0.0" in got[0]


def test_quantile_bounds_are_exact(spark, monkeypatch):
    from codematch.operators import tokens as tk

    monkeypatch.setattr(tk, "frequencies", lambda tokens: tokens)
    monkeypatch.setattr(tk, "stoplist", lambda tokens, lo, hi: (lo, hi))
    assert tk.stoplist_quantiles(spark.range(1, 40_002, 1, 16).toDF("n"), 0.25, 0.95) == (10_001, 38_001)
    none = spark.range(0).toDF("n")
    assert tk.stoplist_quantiles(none, 0.25, 0.95) is none


def test_band_pairs_are_those_of_the_difference_in_doubles(spark, tmp_path):
    values = [0.5, -1e-20, 0.0, -0.0, 1.0, 1.5, 1.5, 1.4999999999999998, 900.1, 900.6, 900.6, 901.1, -0.5, float("nan"), float("inf"), None, 1e300, 1e300]
    spark.createDataFrame([(i, v) for i, v in enumerate(values * 3)] + [(None, 1.0), (3, 1.0)], "p_partkey long, p_retailprice double").repartition(4).write.parquet(f"{tmp_path}/part.parquet")
    want = duckdb.sql(entry.oracle_sql()["join_range_binned"].replace("FROM part a", f"FROM '{tmp_path}/part.parquet/*.parquet' a").replace("JOIN part b", f"JOIN '{tmp_path}/part.parquet/*.parquet' b")).fetchall()
    got = entry.queries()["join_range_binned"](spark, str(tmp_path))
    assert (0, 1) in want and sorted(map(tuple, got.collect())) == sorted(want)
    lists = bands.band_pairs(spark.read.parquet(f"{tmp_path}/part.parquet"), "p_partkey", "p_retailprice", 0.5, most=2)
    assert sorted(map(tuple, lists.collect())) == sorted(want)
