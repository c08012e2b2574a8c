import hashlib
import random
import re

import pytest
from pyspark.sql import functions as F

from codematch.llm import winnowing
from codematch.llm.joins import left_join


def words(text):
    return re.findall(r"[^\x00-\x2F\x3A-\x60\x7B-\x7F]+", re.sub("[A-Z]", lambda m: m[0].lower(), text or ""))


def brute(docs, items, window):
    known = {}
    for i, text in items:
        w = words(text)
        n = min(len(w), window)
        for a in range(len(w) - n + 1 if n and i is not None else 0):
            known.setdefault(tuple(w[a : a + n]), set()).add(str(i))
    lengths = {len(k) for k in known}
    out = []
    for i, text in docs:
        w, hit, ids = words(text), set(), set()
        for n in lengths:
            for a in range(len(w) - n + 1):
                if tuple(w[a : a + n]) in known:
                    hit |= set(range(a, a + n))
                    ids |= known[tuple(w[a : a + n])]
        out.append((i, len(w), len(hit), len(ids), hashlib.sha256(",".join(sorted(ids)).encode()).hexdigest(), bool(hit)))
    return sorted(out, key=repr)


def corpus(seed, short):
    rng = random.Random(seed)
    word = lambda: rng.choice(["ab", "Cd", "é", "42", "xyz", "naïve", "Ünder"]) + str(rng.randint(0, 60))
    items = [(i, " ".join(word() for _ in range(rng.randint(6, 40)))) for i in range(30)]
    if short:
        items += [(100, "one two"), (101, "single"), (102, "one TWO three")]
    items += [(None, "no id here at all but words"), (7, items[3][1]), (55, ""), (56, None), (57, "?!"), (58, items[4][1])]
    docs = []
    for i in range(60):
        own = [word() for _ in range(rng.randint(0, 60))]
        if i % 3 == 0:
            w = (rng.choice(items)[1] or "").split()
            a = rng.randint(0, max(0, len(w) - 1))
            at = rng.randint(0, len(own))
            own[at:at] = [x.upper() for x in w[a : a + rng.randint(1, 40)]]
        docs.append((i, rng.choice([" ", "  ", ", ", "\n"]).join(own)))
    docs += [(200, None), (201, ""), (202, "one"), (203, "Single"), (204, "a one-two!"), (5, docs[0][1]), (0, docs[0][1]), (0, docs[0][1]), (None, docs[3][1]), (None, docs[3][1])]
    return docs + [(300, " ".join([word() for _ in range(20_000)] + items[0][1].split()))], items


@pytest.mark.parametrize(("seed", "short", "most"), [(1, False, 200_000), (2, True, 200_000), (3, True, 2)])
def test_contamination_equals_brute_force(spark, monkeypatch, seed, short, most):
    monkeypatch.setattr(winnowing, "BROADCAST_ROWS", 0 if most < 10 else 500_000)
    docs, items = corpus(seed, short)
    d = spark.createDataFrame([(i, t, 1, "h") for i, t in docs], "doc_id long, text string, h1 int, words string")
    b = spark.createDataFrame([(i, t, 1) for i, t in items], "item_id long, text string, w int")
    got = sorted(map(tuple, winnowing.contamination(d, b, window=6, k=3, most=most, heavy=8).collect()), key=repr)
    assert got == brute(docs, items, 6)
    clean = winnowing.clean_documents(d, b, window=6, k=3)
    assert clean.columns == d.columns
    assert sorted(map(repr, (tuple(r)[:2] for r in clean.collect()))) == sorted(repr((i, t)) for (i, t) in docs if not brute([(i, t)], items, 6)[0][5])


def test_empty_tables(spark):
    d = spark.createDataFrame([(1, "a b c"), (2, None)], "doc_id long, text string")
    none = spark.createDataFrame([], "item_id long, text string")
    got = sorted(map(tuple, winnowing.contamination(d, none).collect()))
    assert got == brute([(1, "a b c"), (2, None)], [], 10)
    assert winnowing.clean_documents(d, none).count() == 2
    some = spark.createDataFrame([(1, "a b c")], "item_id long, text string")
    assert winnowing.contamination(d.limit(0), some).count() == 0 and winnowing.clean_documents(d.limit(0), some).count() == 0


def test_every_long_shared_span_has_a_common_fingerprint(spark):
    rng = random.Random(0)
    rows = []
    for _ in range(200):
        shared = [rng.randint(0, 30) for _ in range(10)]
        a, b = ([rng.randint(0, 30) for _ in range(rng.randint(0, 15))] + shared + [rng.randint(0, 30) for _ in range(rng.randint(0, 15))] for _ in range(2))
        rows.append((a, b))
    marks = lambda c: winnowing.fingerprints(F.col(c), 10, 5)
    assert spark.createDataFrame(rows, "a array<long>, b array<long>").where(F.size(F.array_intersect(marks("a"), marks("b"))) == 0).count() == 0


def test_left_join_is_the_same_beyond_a_broadcast(spark):
    rows = spark.createDataFrame([(i % 7 if i % 10 else None, i) for i in range(300)] + [(3, -i) for i in range(500)], "k long, v long")
    table = spark.createDataFrame([(i, f"x{i}", 40 + 500 * (i == 3)) for i in range(5)] + [(None, "none", 30)], "key long, x string, size long")
    want = sorted(map(repr, left_join(rows, table, {"k": "key"}, "size", "x").collect()))
    for heavy in (1, 2, 1000):
        assert want == sorted(map(repr, left_join(rows, table, {"k": "key"}, "size", "x", most=2, heavy=heavy).collect()))
    assert len(want) == 800 and sum("none" in r for r in want) == 30
