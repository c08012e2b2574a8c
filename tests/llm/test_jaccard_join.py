import itertools
import random
import types

import numpy as np
import pyarrow as pa
import pytest

from codematch.llm import jaccard_join as jj
from codematch.llm.shingles import WordHashes, shingle_set, word_hash, word_hashes


def shingles(text):
    words = (text or "").encode().lower().split()
    return {tuple(words)} if 0 < len(words) < 5 else {tuple(words[i : i + 5]) for i in range(len(words) - 4)}


def brute(rows):
    sets = [shingles(t) for _, t in rows]
    part = list(range(len(rows)))
    for i, j in itertools.combinations(range(len(rows)), 2):
        both = len(sets[i] & sets[j])
        if sets[i] and sets[j] and 100 * both >= 75 * len(sets[i] | sets[j]) and part[i] != part[j]:
            a, b = part[i], part[j]
            part = [a if p == b else p for p in part]
    least = {}
    for p, (i, _) in zip(part, rows, strict=True):
        if i is not None:
            least[p] = min(i, least.get(p, i))
    return sorted((repr(i), len(s), repr(least.get(p) if s else i)) for (i, _), s, p in zip(rows, sets, part, strict=True))


def corpus(seed):
    rng = random.Random(seed)
    word = lambda: f"w{rng.randint(0, 5000)}"
    rows, base = [], []
    for n in (1, 3, 5, 6, 9, 20, 33, 60, 130, 400):
        base.append([word() for _ in range(n)])
    passage = [word() for _ in range(40)]
    for b in base:
        for _ in range(14):
            near = list(b)
            for _ in range(rng.randint(0, max(1, len(b) // 20))):
                near[rng.randrange(len(near))] = word()
            if rng.random() < 0.3:
                near = near[rng.randint(0, len(near) // 8) :]
            rows.append(" ".join(near).upper() if rng.random() < 0.2 else " ".join(near))
    rows += [" ".join([word() for _ in range(30)] + passage) for _ in range(25)]
    rows += [None, "", "  \n", "é É", "É é", " ".join(["same"] * 5000)]
    rng.shuffle(rows)
    numbered = [(i, t) for i, t in enumerate(rows)]
    return numbered + [(None, rows[3]), (3, rows[3]), (7, rows[8])]


@pytest.mark.parametrize(("seed", "small", "hot"), [(1, 8, 10**9), (2, 3, 10**9), (3, 2, 4)])
def test_components_equal_all_pairs(spark, monkeypatch, seed, small, hot):
    monkeypatch.setattr(jj, "SMALL", small)
    monkeypatch.setattr(jj, "LOCAL_LINKS", 0 if seed == 1 else 10**6)
    monkeypatch.setattr(jj, "PIVOTS", 2 if seed == 2 else 64)
    monkeypatch.setattr(jj, "BROADCAST_PIVOTS", 0 if seed == 2 else 10**6)
    if seed > 1:  # pairs within small tiers and across their borders
        monkeypatch.setattr(jj, "TIERS", ((40, 1), (100, 4), (1 << 62, 8)))
        monkeypatch.setattr(jj, "COLUMNS", 4)
    rows = corpus(seed)
    docs = spark.createDataFrame([(i, t, 0, 0) for i, t in rows], "doc_id long, text string, node int, n int")
    got = jj.jaccard_components(docs, frequent_from=4, hot_from=hot).collect()
    assert sorted((repr(r.doc_id), r.n_shingles, repr(r.component_id)) for r in got) == brute(rows)


@pytest.mark.parametrize(("bits", "block", "partners"), [(4, 1024, 256), (64, 2, 1)])
def test_digests_that_clash_and_groups_dealt_over_blocks(spark, monkeypatch, bits, block, partners):
    monkeypatch.setattr(jj, "SMALL", 2)
    monkeypatch.setattr(jj, "PARTNERS", partners)
    rows = corpus(5)
    docs = spark.createDataFrame(rows, "doc_id long, text string")
    got = jj.jaccard_components(docs, frequent_from=10**9, block=block, digest_bits=bits).collect()
    assert sorted((repr(r.doc_id), r.n_shingles, repr(r.component_id)) for r in got) == brute(rows)


def test_pairs_of_a_group_meet_once_and_few_rows_come_out(spark):
    """Documents that share one long passage: no pair is alike, and the pairs that come out don't grow with the keys they share."""
    members = [(k, i, 100, i) for k in range(30) for i in range(40)]
    rest = spark.createDataFrame(members, "key long, node long, n long, part long")
    merged = jj._merged(rest.select("key", "node", "n"))
    assert merged.select("key").distinct().count() == 1 and merged.count() == 40
    x, y = jj._met(merged.withColumn("part", merged.node), 75, 7)
    met = x.alias("x").join(y.alias("y"), ["key", "size", "i", "j"]).where("x.node < y.node")
    assert met.count() == met.select("x.node", "y.node").distinct().count() == 40 * 39 // 2


def test_empty_table(spark):
    assert jj.jaccard_components(spark.createDataFrame([], "doc_id long, text string")).count() == 0


def test_sketch_bounds_the_difference_and_parts_meet():
    rng, cache = np.random.default_rng(0), WordHashes()
    none = (np.empty(0, np.uint64), np.empty(0, np.int64))
    for _ in range(200):
        n = int(rng.integers(1, 700))
        words = rng.integers(0, 10**6, n).tolist()
        other = list(words)
        for _ in range(int(rng.integers(0, 1 + n // 40))):
            other[int(rng.integers(n))] = int(rng.integers(10**6))
        a, b = (shingle_set(" ".join(map(str, x)).encode(), 5, cache) for x in (words, other))
        apart = len(np.setxor1d(a, b))
        assert jj.sketch_distance(jj.bit_sketch(a), jj.bit_sketch(b)) <= apart
        x, y = (jj.folded(jj.bit_sketch(s), 16) for s in (a, b))
        assert int(np.bitwise_count((x ^ y).view(np.uint64)).sum()) <= apart
        common = len(np.intersect1d(a, b))
        if 100 * common >= 75 * (len(a) + len(b) - common):
            keys = [{int(k) for band, top, need in jj.bands(len(s), 75) for k in jj.choose(jj.parities(s, band, top), need, none)} for s in (a, b)]
            assert keys[0] & keys[1]


def test_similar_sets_meet_in_the_tier_of_the_larger():
    for n in [1, 1023, 1024, 4095, 4096, 12287, 12288, 10**6]:
        own = jj.tiers(n, 75)[0]
        assert n < jj.TIERS[own][0] and all(own in jj.tiers(k, 75) for k in range(-(-n * 75 // 100), n + 1, max(1, n // 50)))
        assert 8 * len(jj.bit_sketch(np.arange(n, dtype=np.uint64))) >= max(n, *(64 * jj.TIERS[i][1] for i in jj.tiers(n, 75)))


def test_keys_of_one_passage_leave_a_bucket_as_one_group():
    keys, nodes = np.repeat(np.arange(20, dtype=np.uint64), 10), np.tile(np.arange(100, 110), 20)
    row = [pa.array([0], pa.int32()), *(pa.array([x.tobytes()], pa.binary()) for x in (keys, nodes, np.full(200, 50, np.int32)))]
    batch = pa.RecordBatch.from_arrays(row, names=["bucket", "keys", "nodes", "sizes"])
    for very, rows in (([], 10), ([3], 20)):
        hot = types.SimpleNamespace(value=(np.array(very, np.uint64), np.ones(len(very), np.int64)))
        found = pa.Table.from_batches(list(jj._group(75, hot)(iter([batch])))).to_pylist()
        assert len(found) == rows and {r["a"] for r in found} == set(range(100, 110)) and {r["kind"] for r in found} == {1}


def test_words_have_one_hash_on_every_way():
    rng = random.Random(3)
    texts = [bytes(rng.choice(b"ab \t\n\r\x0b\x0c\x1c\x85\xa0\0\xff") for _ in range(rng.randint(0, 90))) for _ in range(500)]
    texts += [b"", b" ", b"a\0 a \0a", b"x" * 5000, b" ".join(b"q" * k for k in range(70)), ("\u4e2d\u6587" * 300).encode()]
    for text in texts:
        assert word_hashes(text).tolist() == [word_hash(w) for w in text.split()]
    long = " ".join(f"Word{i}" for i in range(300))  # by the bytes of the text; its passages by the table of words
    parts = [long.split()[i : i + 20] for i in range(281)]
    alone = [shingle_set(" ".join(p).encode(), 5, WordHashes()) for p in parts]
    assert np.array_equal(np.unique(np.concatenate(alone)), shingle_set(long.encode(), 5, WordHashes()))


def test_small_torn_groups_meet_whole_and_send_a_member_once(spark, monkeypatch):
    """Thirty documents of one passage and four of others: no turns of pivots, one sketch for each row of the group, the pairs of all tiers."""
    rng, words = random.Random(4), []
    for size in (60, 900, 1100, 5000):
        own = [f"w{rng.randint(0, 10**6)}" for _ in range(size)]
        words += [own, [*own[: size // 30], *own[size // 20 :]]]
    sets = [shingle_set(" ".join(w).encode(), 5, WordHashes()) for w in words]
    nodes = spark.createDataFrame([(i, bytearray(jj.bit_sketch(s))) for i, s in enumerate(sets)], "node long, sketch binary")
    rest = spark.createDataFrame([(1, i, i if i != 3 else 2, len(s)) for i, s in enumerate(sets)], "key long, node long, part long, n long")
    assert sorted(map(tuple, jj._pairs_of_whole(rest, nodes, 75).collect())) == [(0, 1), (4, 5), (6, 7)]
    passage = [f"p{i}" for i in range(40)]
    rows = [(i, " ".join([*(f"d{i}x{j}" for j in range(60)), *passage])) for i in range(30)]
    rows += [(40 + i, " ".join(f"d{i % 2}x{j}" for j in range(i, 60))) for i in range(4)]
    monkeypatch.setattr(jj, "_pivot_ties", lambda *a: pytest.fail("a group of MEET members or fewer takes no turn"))
    got = jj.jaccard_components(spark.createDataFrame(rows, "doc_id long, text string")).collect()
    assert sorted((repr(r.doc_id), r.n_shingles, repr(r.component_id)) for r in got) == brute(rows)


@pytest.mark.parametrize("meet", [0, 12])
def test_large_torn_groups_take_turns_as_before(spark, monkeypatch, meet):
    monkeypatch.setattr(jj, "SMALL", 2)
    monkeypatch.setattr(jj, "MEET", meet)
    monkeypatch.setattr(jj, "PIVOTS", 3)
    rows = corpus(6)
    got = jj.jaccard_components(spark.createDataFrame(rows, "doc_id long, text string")).collect()
    assert sorted((repr(r.doc_id), r.n_shingles, repr(r.component_id)) for r in got) == brute(rows)
