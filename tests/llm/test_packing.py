import random

from codematch.llm import packing


def plain(sizes, sources, clusters, capacity):
    """Best fit by looking at every bin."""
    bins, out = [], []
    for size, s, c in zip(sizes, sources, clusters, strict=True):
        fit = [(b["room"], i) for i, b in enumerate(bins) if b["room"] >= size and (s is None or s not in b["s"]) and (c is None or c not in b["c"])]
        if fit:
            i = min(fit)[1]
        else:
            i = len(bins)
            bins.append({"room": capacity, "s": set(), "c": set()})
        bins[i]["room"] -= size
        bins[i]["s"].add(s)
        bins[i]["c"].add(c)
        out.append(i)
    return out


def test_best_fit_is_the_tightest_compatible_bin():
    rng = random.Random(1)
    for _ in range(30):
        n = rng.randint(0, 120)
        sizes = [rng.randint(1, 100) for _ in range(n)]
        sources = [rng.choice([None, "a", "a", "b", "c", "d"]) for _ in range(n)]
        clusters = [rng.choice([None, 1, 2, *range(10, 60)]) for _ in range(n)]
        assert packing.best_fit(sizes, sources, clusters, 100) == plain(sizes, sources, clusters, 100)


def test_pack_keeps_every_word(spark):
    rng = random.Random(2)
    texts = [None, "", " ", "w " * 5000, "w " * 2047, *(" ".join(str(rng.random()) for _ in range(rng.randint(1, 900))) for _ in range(80))]
    rows = [(i if i % 9 else None, t, rng.choice(["hot", "hot", f"s{i % 7}", None]), 0) for i, t in enumerate(texts)]
    rows += rows[5:8]
    out = packing.pack(spark.createDataFrame(rows, "doc_id long, text string, source string, bin_id long"), shard_rows=40).collect()
    assert sum(r.length for r in out) == sum(len((t or "").split()) + 1 for _, t, _, _ in rows)
    bins = {}
    for r in out:
        bins.setdefault(r.bin_id, []).append(r)
    for members in bins.values():
        assert sum(r.length for r in members) <= packing.CAPACITY
        for c in ("source", "cluster"):
            known = [r[c] for r in members if r[c] is not None]
            assert len(known) == len(set(known))
    assert packing.pack(spark.createDataFrame([], "doc_id long, text string, source string")).count() == 0


def test_many_equal_rows_are_dealt_over_shards(spark):
    rows = [(None, "same words here", None)] * 300 + [(7, "w " * 50, "s")] * 40 + [(8, "x " * 25, "t")] * 3
    docs = spark.createDataFrame(rows, "doc_id long, text string, source string")
    got = packing.pack(docs, capacity=20, shard_rows=20, copies_at_once=7).collect()
    assert sum(r.length for r in got) == 300 * 4 + 40 * 51 + 3 * 26
    assert len({r.bin_id for r in got if r.length == 20}) == sum(r.length == 20 for r in got) == 40 * 2 + 3
    assert len({r.bin_id >> 32 for r in got if r.bin_id >= 0}) > 10
    own = [r.bin_id for r in got if r.doc_id is None]
    assert len(own) == len(set(own)) == 300  # copies of a cluster never share a bin
    empty = spark.createDataFrame([], docs.schema)
    assert packing.pack(empty).count() == 0
