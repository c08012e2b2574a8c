"""Worked examples and invariants of the methods, on hand-made points and small tables."""

import itertools
import tracemalloc

import numpy as np
import pytest
from pyspark.sql import functions as F

from codematch.operators import encode as en, graph, kmeans, metrics, prep, querysets, rotate, score, search, tokens as tk, train, vectors
from codematch.operators.baselines import binary, brute, hashes, rawdist
from codematch.operators.model import CodeModel, anchor

X = {1: (1.0, 0.0, 9.0, 10.0), 2: (0.0, 1.0, 10.0, 9.0), 3: (1.0, 0.0, 1.0, 0.0)}


@pytest.fixture(scope="module")
def toy():
    corners = np.array([[0.0, 0.0], [10.0, 10.0]])
    return CodeModel(m=2, coarse=np.stack([corners, corners]), sub=np.array([[[1.0, 0], [0, 1.0]], [[-1.0, 0], [0, -1.0]]]))


@pytest.fixture(scope="module")
def points(spark):
    return spark.createDataFrame([(i, list(v)) for i, v in X.items()], "id long, vec array<double>")


@pytest.fixture(scope="module")
def emb(spark, sf):
    return vectors.embeddings(spark, sf).cache()


def test_toy_codes_and_hits(spark, toy, points):
    codes = en.encode(points, toy)
    assert {r.id: (r.c1, r.c2, list(r.fine)) for r in codes.collect()} == {1: (0, 1, [0, 0]), 2: (0, 1, [1, 1]), 3: (0, 0, [0, 1])}
    assert {(r.a, r.b): r.hits for r in graph.pair_hits(tk.flatten(codes)).collect()} == {(1, 3): 1}
    assert score.sdc_tables(toy)[0, 0, 1] == 2.0


def test_set_search_excludes_members(spark, toy, points):
    t = tk.flatten(en.encode(points, toy))
    q = t.where("id < 3").select(F.lit(7).cast("long").alias("set_id"), "token")
    assert {r.id: r.score for r in querysets.batch_search(q, t).collect()} == {1: 2, 2: 2, 3: 1}
    members = spark.createDataFrame([(7, 1), (7, 2)], "set_id long, id long")
    assert [r.id for r in querysets.batch_search(q, t, members=members).collect()] == [3]


def test_cells_are_visited_in_order():
    got = search.visit([np.array([1.0, 4.0]), np.array([2.0, 3.0])], {c: 1 for c in itertools.product(range(2), range(2))}, 3)
    assert [(c1, c2, d) for c1, c2, d, _ in got] == [(0, 0, 3.0), (0, 1, 4.0), (1, 0, 6.0)]
    rng = np.random.default_rng(0)
    for _ in range(50):
        one, two = rng.random(6), rng.random(6)
        sizes = {(i, j): int(n) for (i, j), n in zip(itertools.product(range(6), range(6)), rng.integers(0, 3, 36)) if n}
        got = search.visit([one, two], sizes, 10**9)
        assert sorted((c1, c2) for c1, c2, *_ in got) == sorted(sizes)
        assert all(a[2] <= b[2] for a, b in itertools.pairwise(got))


@pytest.mark.parametrize("method", ["star", "label", "local"])
def test_components(spark, method):
    rows = [(1, 2), (2, 3), (7, 8), (8, 7), (20, 21)] + [(i, i + 1) for i in range(100, 163)]
    pairs = spark.createDataFrame(rows, "a long, b long")
    nodes = spark.createDataFrame([(5,), (1,)], "id long")
    got = {r.id: r.component for r in graph.components(pairs, method=method).collect()}
    assert got == graph.union_find(rows)
    assert {r.id: r.component for r in graph.components(pairs, nodes, method).collect()} == {5: 5, 1: 1}


def test_strict_edges(spark):
    pairs = spark.createDataFrame([(1, 2, 4), (2, 3, 4), (3, 4, 3)], "a long, b long, hits long")
    assert len({r.component for r in graph.components(graph.edges(pairs, 3)).collect()}) == 1
    assert graph.edges(pairs, 3).count() == 2 and graph.edges(pairs, 3, strict=False).count() == 3


def test_join_count_equals_all_pairs_and_prefix(spark, emb):
    codes = en.encode(emb, anchor(emb, 8, 8, 16)).cache()
    t = tk.flatten(codes)
    joined = {(r.a, r.b): r.hits for r in graph.pair_hits(t).collect()}
    assert joined == {(r.a, r.b): r.hits for r in graph.pair_hits_naive(codes, 8).collect()}
    for h in (2, 4, 6):
        assert {k: n for k, n in joined.items() if n >= h} == {(r.a, r.b): r.hits for r in graph.pair_hits_prefix(t, 8, h).collect()}
    assert tk.stoplist(t, 0, 10**9).count() == t.count()


def test_training_lowers_distortion_and_rotations_are_orthogonal(spark, emb):
    history = []
    kmeans.fit(emb, 8, 4, iters=6, stop=0.0, history=history)
    assert all(b <= a + 1e-9 for a, b in itertools.pairwise(history))
    model = train.fit(emb, 3, 8, 8, iters=4)
    assert metrics.orthogonality(model.rot) < 1e-9
    worst = train.fit_pq(emb, 8, 8, 0).coarse  # shape only
    assert worst.shape == (1, 1, 64)
    plain, local = (metrics.distortion(emb, m).first().total for m in (train.fit_pq(emb, 8, 8, 4), train.fit(emb, 3, 8, 8, iters=4, codebooks="local")))
    assert metrics.distortion(emb, model).first().total < plain and local < plain


def test_alternation_and_allocation():
    rng = np.random.default_rng(1)
    res = rng.normal(size=(400, 8)) @ np.diag([5, 4, 3, 2, 1, 1, 0.5, 0.2])
    r, _, history = rotate.alternate(res, 4, 8)
    assert history[-1] < history[0] and np.abs(r.T @ r - np.eye(8)).max() < 1e-9
    values = np.array([9.0, 7, 5, 3, 1, 0.5, 0.3, 0.1])
    perm = prep.allocate(values, 4)
    assert sorted(perm) == list(range(8))
    spread = lambda p: np.ptp(np.log(values[p]).reshape(4, 2).sum(1))
    assert spread(perm) < spread(np.arange(8))


def test_model_survives_saving(spark, emb, tmp_path):
    model = train.fit(emb, 3, 8, 8, iters=2, pca=16)
    model.save(spark, f"{tmp_path}/m")
    again = CodeModel.load(spark, f"{tmp_path}/m")
    x = np.array([r.vec for r in emb.limit(20).collect()])
    assert all((a == b).all() for a, b in zip(model.encode(x), again.encode(x), strict=True))
    with pytest.raises(ValueError):
        CodeModel(m=3, coarse=model.coarse, sub=model.sub)


def test_codes_beat_chance_and_distances_beat_hits(spark, emb):
    q, db = emb.where("id % 10 = 0"), emb.where("id % 10 <> 0")
    truth = brute.knn(q, db, 1).select("qid", "id")
    model = train.fit(emb, 2, 8, 16, iters=6)
    from codematch.operators.baselines import rawdist

    codes = en.encode(db, model)
    at = lambda got: metrics.recall_at(got, truth, [50]).first().recall
    by_hits, by_distance, floor = at(search.knn(q, model, codes, 50, 10**9)), at(rawdist.knn(q, model, codes, 50, 10**9)), at(brute.random_rank(q, db, 50))
    assert by_distance >= by_hits > floor


def test_precision_rises_and_recall_falls_with_the_threshold(spark):
    pairs = spark.createDataFrame([(1, 2, 8), (1, 3, 5), (2, 3, 4), (4, 5, 7)], "a long, b long, s long")
    truth = spark.createDataFrame([(1, 2), (4, 5), (6, 7)], "a long, b long")
    got = metrics.pair_pr(pairs, truth, [4, 6, 8]).orderBy("threshold").collect()
    assert [(r.precision, r.recall) for r in got] == [(0.5, 0.666667), (1.0, 0.666667), (1.0, 0.333333)]


def test_binary_codes(spark, emb):
    codes = binary.encode(emb, *[hashes.lsh(64, 64)[i] for i in (0, 2)]).cache()
    near = {(r.a, r.b): r.dist for r in binary.hamming_pairs(codes, 17, 64).collect()}
    words = {r.id: r.words for r in codes.collect()}
    want = {(a, b): d for a, b in itertools.combinations(sorted(words), 2) if (d := sum((x ^ y).bit_count() for x, y in zip(words[a], words[b], strict=True))) <= 17}
    assert near == want
    for made in (hashes.itq(emb, 32, 5), hashes.spectral(emb, 32), hashes.sequential(emb, 16)):
        share = made[2](np.array([r.vec for r in emb.collect()])).mean(0)
        assert ((share > 0.1) & (share < 0.9)).mean() > 0.8


def test_bad_vectors_are_errors(spark, toy):
    with pytest.raises(Exception, match="finite numbers"):
        en.encode(spark.createDataFrame([(1, [1.0, 2.0])], "id long, vec array<double>"), toy).collect()
    assert en.encode(spark.createDataFrame([(1, None)], "id long, vec array<double>"), toy).count() == 0


def test_streams(spark, sf, tmp_path, toy, points):
    from codematch.streaming import stream

    events = spark.read.parquet(f"{sf}/events.parquet")
    events.orderBy("ts").repartition(3).write.parquet(f"{tmp_path}/ev")
    q = stream.windowed_counts(stream.events_stream(spark, f"{tmp_path}/ev", events.schema, "400 days"), "6 hours").writeStream.format("memory").queryName("w").outputMode("complete").trigger(availableNow=True).start()
    q.awaitTermination()
    batch = events.withColumn("ts", F.col("ts").cast("timestamp")).groupBy(F.window("ts", "6 hours"), "event_type").count()
    assert spark.table("w").agg(F.sum("n")).first()[0] == events.count() and spark.table("w").count() == batch.count()
    points.write.parquet(f"{tmp_path}/p")
    src = spark.readStream.schema(points.schema).parquet(f"{tmp_path}/p")
    stream.append_codes(src, toy, f"{tmp_path}/codes", f"{tmp_path}/ck").awaitTermination()
    assert {(r.id, r.c1, r.c2) for r in spark.read.parquet(f"{tmp_path}/codes").collect()} == {(1, 0, 1), (2, 0, 1), (3, 0, 0)}
    rows = spark.createDataFrame([(1, 0, 0, [1, 2], 10), (2, 0, 0, [1, 2], 20), (3, 0, 0, [5, 6], 30), (4, 1, 0, [1, 2], 40)], "id long, c1 int, c2 int, fine array<int>, s int")
    rows.select("id", "c1", "c2", "fine", F.timestamp_seconds("s").alias("ts")).coalesce(1).write.parquet(f"{tmp_path}/c")
    live = spark.readStream.schema("id long, c1 int, c2 int, fine array<int>, ts timestamp").parquet(f"{tmp_path}/c").withWatermark("ts", "1 minute")
    q = stream.suppress_near_repeats(live, 2, 1).writeStream.format("memory").queryName("s").outputMode("append").trigger(availableNow=True).start()
    q.awaitTermination()
    assert {r.id for r in spark.table("s").collect()} == {1, 3, 4}


def test_clusters_count_tokens_however_frequent(spark, sf, tmp_path):
    from codematch.plans.methods import Q

    docs = spark.read.parquet(f"{sf}/documents.parquet").where("doc_id < 100")
    text = docs.where("n_chars > 1000").orderBy("doc_id").first().text
    copies = spark.range(1000, 1250).select(F.col("id").alias("doc_id"), F.lit(text).alias("text"), F.lit("en").alias("lang"))
    docs.select("doc_id", "text", "lang").unionByName(copies).write.parquet(f"{tmp_path}/documents.parquet")
    found = {r.id: r.component for r in Q["cluster_documents"](spark, str(tmp_path)).collect()}
    assert len({found[i] for i in range(1000, 1250)}) == 1
    assert {(r.a, r.b) for r in Q["edges_strict"](spark, str(tmp_path)).where("a >= 1000").collect()} == set(itertools.combinations(range(1000, 1250), 2))


def test_pairs_by_blocks_equal_all_pairs(spark, emb):
    codes = en.encode(emb, anchor(emb, 8, 8, 16)).cache()
    pairs = {(r.a, r.b): r.hits for r in graph.pair_hits_naive(codes, 8).collect()}
    twins = codes.unionByName(codes.where("id % 3 = 0").withColumn("id", F.col("id") + 10**6))
    for h in (1, 2, 4, 6):
        got = graph.pair_hits_blocks(codes, 8, h).collect()
        assert len(got) == len({(r.a, r.b) for r in got}) and {(r.a, r.b): r.hits for r in got} == {p: n for p, n in pairs.items() if n >= h}
    want = graph.union_find([(r.a, r.b) for r in graph.pair_hits_naive(twins, 8).where("hits > 3").collect()])
    assert {r.id: r.component for r in graph.cluster_all(twins, 8, 3).where("id <> component").collect()} == {i: c for i, c in want.items() if i != c}


def test_one_coarse_space_ranks_by_quantized_distance(spark, emb):
    model = anchor(emb, 6, 8, 16, halves=1)
    q, db = emb.where("id % 10 = 0"), emb.where("id % 10 <> 0")
    codes = en.encode(db, model)
    got = {(r.qid, r.id): r.score for r in rawdist.knn(q, model, codes, 5, 10**9).collect()}
    rows = codes.collect()
    back = model.decode(np.array([[r.c1] for r in rows]), np.array([list(r.fine) for r in rows]))
    for r in q.collect():
        d = ((np.array(r.vec) - back) ** 2).sum(1)
        best = sorted(zip(np.round(d, 9), (x.id for x in rows), strict=True))[:5]
        assert all(abs(got[r.id, i] - v) < 1e-6 for v, i in best)
    near = search.knn(q, model, codes, 5, 20)
    assert near.where("qid = id").count() == 0 and near.groupBy("qid").count().where("count > 5").count() == 0


def test_only_visited_clusters_are_encoded(spark, emb):
    model = anchor(emb, 8, 8, 16, rotate=True)
    q, sizes = emb.where("id % 10 = 0"), search.cell_sizes(en.encode(emb, model))
    cells = search.visited_cells(q, model, sizes, 30, codes=True).collect()
    probes = {(r.id, r.half, r.c): list(r.fine) for r in en.encode_probes(q, model, model.K).collect()}
    assert cells and all(list(r.qfine) == probes[r.qid, 0, r.c1] + probes[r.qid, 1, r.c2] for r in cells)


def test_many_clusters_take_bounded_memory(spark, emb):
    """Encoding and search with K = 1024: temporaries don't grow with rows times clusters."""
    rng = np.random.default_rng(0)
    model = CodeModel(m=8, coarse=rng.normal(size=(2, 1024, 32)), sub=rng.normal(size=(8, 16, 8)))
    x = rng.normal(size=(20_000, 64))
    tracemalloc.start()
    c, _ = model.encode(x)
    peak = tracemalloc.get_traced_memory()[1]
    tracemalloc.stop()
    assert peak < 120 << 20  # all distances at once would be 160 MB a half, and as much again for each temporary
    assert (c[:50, 0] == ((x[:50, None, :32] - model.coarse[0]) ** 2).sum(2).argmin(1)).all()
    codes = en.encode(emb, model)
    got = search.knn(emb.where("id % 50 = 0"), model, codes, 5, 40).collect()
    assert got and max(r.rnk for r in got) <= 5


def test_learned_hashes_come_from_all_rows(spark, emb):
    x = np.array([r.vec for r in emb.orderBy("id").collect()])
    mean = x.mean(0)
    values, axes = np.linalg.eigh(np.cov(x.T, bias=True))
    axes = axes[:, np.argsort(-values)][:, :8]
    d, bits, of = hashes.pca_signs(emb, 8)
    same = (of(x) == ((x - mean) @ axes > 0)).mean(0)
    assert (d, bits) == (64, 8) and (np.maximum(same, 1 - same) > 0.999).all()  # an axis has no sign
    _, _, spread = hashes.spectral(emb, 16)
    assert spread(x).shape == (len(x), 16)
    _, _, rotated = hashes.itq(emb, 8, iters=20)
    v = (x - mean) @ prep.eigen(prep.covariance(emb)[2])[1][:, :8]
    r, _ = np.linalg.qr(np.random.default_rng(0).normal(size=(8, 8)))
    for _ in range(20):
        u, _, wt = np.linalg.svd(v.T @ np.where(v @ r >= 0, 1.0, -1.0))
        before, r = r, u @ wt
        if np.abs(r - before).max() < 1e-4:
            break
    assert (rotated(x) == (v @ r >= 0)).mean() > 0.999


def test_query_sets_beyond_the_bound_are_refused(spark, emb, monkeypatch):
    monkeypatch.setattr(brute, "MOST_QUERIES", 3)
    for f in (brute.random_rank, brute.knn):
        with pytest.raises(ValueError):
            f(emb.limit(4), emb, 2)


def test_one_list_is_deduplicated_without_spark(spark, emb):
    codes = en.encode(emb, anchor(emb, 4, 8, 4))
    results = emb.where("id < 60").select(F.lit(1).cast("long").alias("qid"), "id", (60 - F.col("id")).cast("int").alias("rnk"), (F.col("id") % 7).alias("length"))
    own = results.join(codes, "id").collect()
    for keep in ("best_rank", "smallest_id", "longest"):
        want = {r.id: r.component for r in graph.dedup_results(results, codes, 8, 3, keep=keep).collect()}
        rows, name = graph.dedup_list([r.asDict() for r in own], 8, 3, keep=keep)
        assert {r["id"]: rows[c]["id"] for r, c in zip(rows, name, strict=True)} == want and len(set(want.values())) < 60


def test_turns_of_long_conversations_keep_their_ids(spark, tmp_path):
    rows = [(1, 1000, "user", "a b"), (2, 0, "user", "c d")]
    spark.createDataFrame(rows, "conv_id long, turn long, role string, text string").write.parquet(f"{tmp_path}/conversations.parquet")
    assert vectors.turns(spark, str(tmp_path)).select("id").distinct().count() == 2
