"""Comparing block against block gives what joins give."""

import random

from pyspark.sql import functions as F

from codematch.operators import blocks, graph, querysets, tokens as tk
from codematch.operators.baselines import binary

KIND = "id long, c1 int, c2 int, fine array<smallint>, set_id string"


def some_codes(spark, n=120):
    rng = random.Random(3)
    rows = [(i, rng.randrange(3), rng.randrange(3), [rng.randrange(3) for _ in range(8)], [None, "a", "b"][i % 3]) for i in range(n)]
    return spark.createDataFrame(rows + [(1000 + i, *rows[i][1:]) for i in range(30)], KIND)


def rows(df):
    return sorted(map(tuple, df.collect()), key=repr)


def test_counts_of_hits_equal_the_join(spark, monkeypatch):
    monkeypatch.setattr(blocks, "CELLS", 50)
    codes = some_codes(spark)
    pairs = graph.pair_hits(tk.flatten(codes), 2)
    assert rows(blocks.count_hits(codes, 8, 2)) == rows(pairs.groupBy("hits").count())


def test_near_bits_and_their_counts_equal_all_pairs(spark):
    rng = random.Random(4)
    words = {i: [rng.getrandbits(32) & 0xF0F0F | 1 << 31, rng.getrandbits(32) & 3, rng.getrandbits(6)] for i in range(150)}
    words |= {500 + i: words[i] for i in range(10)}
    codes = spark.createDataFrame(list(words.items()), "id long, words array<long>")
    want = [(a, b, sum((x ^ y).bit_count() for x, y in zip(words[a], words[b], strict=True))) for a in words for b in words if a < b]
    want = sorted(p for p in want if p[2] <= 9)
    assert want and rows(blocks.near_bits(codes, 9, 70)) == sorted(want, key=repr) == rows(binary.hamming_pairs(codes, 9, 70).select("a", "b", "dist"))
    assert dict(blocks.count_distances(codes, 9, 70).collect()) == {s: n for s in range(10) if (n := sum(p[2] == s for p in want))}


def test_pooled_hits_equal_pools_of_single_queries(spark):
    codes = some_codes(spark)
    q, db = codes.where("id % 10 < 3"), codes.where("id % 10 >= 3")
    single = querysets.query_scores(tk.flatten(q, ("set_id", "id")).withColumnRenamed("id", "qid"), tk.flatten(db))
    want = single.groupBy("set_id", "id").agg(F.max("score").cast("long").alias("most"), F.count(F.lit(1)).alias("reached"))
    assert rows(blocks.pooled_hits(q, db, 8)) == rows(want)


def test_recommendations_equal_the_batch_search(spark, monkeypatch):
    monkeypatch.setattr(querysets, "ITEMS", 40)
    codes = some_codes(spark).drop("set_id")
    bought = codes.select((F.col("id") % 7).alias("set_id"), "id").where("id % 11 < 2")
    t = tk.flatten(codes)
    want = querysets.batch_search(bought.join(t, "id").select("set_id", "token"), t, top=10, members=bought)
    columns = ["set_id", "id", "score", "rnk"]
    assert rows(querysets.recommend(bought, codes, 8, 10).select(columns)) == rows(want.select(columns))


def test_the_local_method_gives_components_beyond_its_bound(spark, monkeypatch):
    monkeypatch.setattr(graph, "LOCAL_EDGES", 20)
    pairs = spark.createDataFrame([(i, i + 2) for i in range(60)], "a long, b long")
    assert rows(graph.components(pairs, method="local")) == [(i, i % 2) for i in sorted(range(62), key=lambda i: repr((i, i % 2)))]


def test_pairs_of_hits_equal_the_join(spark, monkeypatch):
    monkeypatch.setattr(blocks, "CELLS", 50)
    monkeypatch.setattr(blocks, "OUT_ROWS", 7)
    codes = some_codes(spark)
    got = blocks.hit_pairs(codes, 8, 2)
    assert rows(got) == rows(graph.pair_hits(tk.flatten(codes), 2).select("a", "b", "hits"))


def test_forests_connect_what_all_pairs_connect(spark, monkeypatch):
    monkeypatch.setattr(blocks, "CELLS", 50)
    monkeypatch.setattr(blocks, "EDGES", 40)
    codes = some_codes(spark)
    tokens = tk.flatten(codes)
    pairs = graph.pair_hits(tk.stoplist(tokens, 5, 40), 2).cache()
    place = F.shiftright("token", 16).bitwiseAND(F.lit(0xFFFF)).cast("int")
    kept = tk.stoplist(tokens, 5, 40).groupBy("id").agg(F.collect_set(place).alias("kept"))
    fine = F.transform("fine", lambda f, i: F.when(F.array_contains("kept", i), f).otherwise(F.lit(blocks.MARK).cast("smallint")))
    counts, forest = blocks.hit_forests(codes.join(kept, "id").withColumn("fine", fine), 8, 2, block=30)
    assert rows(counts) == rows(pairs.groupBy("hits").count())
    every, few = [(p.a, p.b, p.hits) for p in pairs.collect()], [(p.a, p.b, p.s) for p in forest.collect()]
    assert len(few) < len(every) / 2
    for least in range(2, 9):
        assert graph.union_find([p[:2] for p in few if p[2] >= least]) == graph.union_find([p[:2] for p in every if p[2] >= least])


def test_hits_are_counted_without_a_row_or_a_comparison_for_each_pair(spark, monkeypatch):
    compared = []
    monkeypatch.setattr(blocks, "meet", lambda *a, **k: compared.append(a))
    rng = random.Random(5)
    codes = spark.createDataFrame([(i, rng.randrange(4), rng.randrange(4), [rng.choice((0, 0, 1, 31, 100)) for _ in range(16)], None) for i in range(400)], KIND)
    codes = codes.unionAll(codes.where("id < 40").selectExpr("id + 1000", "c1", "c2", "fine", "set_id"))
    pairs = graph.pair_hits(tk.flatten(codes), 5)
    assert rows(blocks.count_hits(codes, 16, 5)) == rows(pairs.groupBy("hits").count()) and not compared


def test_near_sets_of_grams_are_those_of_all_pairs(spark, monkeypatch):
    from codematch.operators import grams

    for name, value in (("FREQUENT", 2), ("LISTED", 30), ("PACKED", 500), ("HELD", 64)):
        monkeypatch.setattr(grams, name, value)
    rng = random.Random(6)
    words = ["Été", "b", "c2", "d", "e", "Über", "g", "h"]
    texts = {i: [rng.choice(words) for _ in range(rng.choice((0, 1, 2, 3, 5, 40)))] for i in range(80)}
    for i in range(80, 160):
        w = list(texts[rng.randrange(i)])
        for _ in range(rng.randrange(4)):
            if w:
                w[rng.randrange(len(w))] = rng.choice(words)
        texts[i] = w
    df = spark.createDataFrame([(i, (" ,"[i % 2]).join(w) + "!") for i, w in texts.items()] + [(900, None)], "id long, text string").repartition(3)
    sets = {i: {tuple(x.lower() for x in w[j : j + 3]) for j in range(len(w) - 2)} for i, w in texts.items()}
    want = {(a, b) for a in sets for b in sets if a < b and sets[a] and sets[b] and 10 * len(sets[a] & sets[b]) >= 7 * len(sets[a] | sets[b])}
    members, near = grams.near_classes(df)
    of, near = dict(members.collect()), {tuple(p) for p in near.collect()}
    assert of.keys() == {i for i, s in sets.items() if s}
    assert len(want) > 20 and want == {(a, b) for a in of for b in of if a < b and (of[a] == of[b] or (min(of[a], of[b]), max(of[a], of[b])) in near)}


def test_the_best_items_are_found_without_scores_of_all(spark, monkeypatch):
    rng = random.Random(8)
    kinds = [(rng.randrange(3), rng.randrange(3), [rng.randrange(4) for _ in range(8)]) for _ in range(150)]
    codes = spark.createDataFrame([(i * 7 % 601, *rng.choice(kinds)) for i in range(601)], "id long, c1 int, c2 int, fine array<smallint>")
    bought = spark.createDataFrame([(s, rng.randrange(640)) for s in range(30) for _ in range(s)] + [(40, i) for i in range(601)], "set_id long, id long")
    t = tk.flatten(codes)
    once = bought.distinct()
    want = rows(querysets.batch_search(once.join(t, "id").select("set_id", "token"), t, top=10, members=once).select("set_id", "id", "score", "rnk"))
    monkeypatch.setattr(querysets, "FIRST", 4)
    for size in (2_000_000, 100):
        monkeypatch.setattr(querysets, "ITEMS", size)
        assert rows(querysets.recommend(bought, codes, 8, 10).select("set_id", "id", "score", "rnk")) == want
