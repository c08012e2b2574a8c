import hashlib
import random
from collections import Counter

import numpy as np
import pytest

from codematch.llm import repeats


def brute(texts, span):
    data = [(t or "").encode() for t in texts]
    seen = Counter(d[i : i + span] for d in data for i in range(len(d) - span + 1))
    out = []
    for d in data:
        gone = np.zeros(len(d), bool)
        for i in range(len(d) - span + 1):
            if seen[d[i : i + span]] > 1:
                gone[i : i + span] = True
        runs = int((np.diff(np.r_[0, gone.astype(int)]) == 1).sum())
        kept = bytes(np.frombuffer(d, np.uint8)[~gone])
        out.append((len(d), int(gone.sum()), runs, hashlib.sha256(kept).hexdigest()))
    return out


def corpus(seed=3):
    rng = random.Random(seed)
    word = lambda: "".join(rng.choice("abcdefghé") for _ in range(rng.randint(1, 7)))
    passages = [" ".join(word() for _ in range(rng.randint(20, 60))) for _ in range(4)]
    texts = [None, "", "x", "ab" * 400, "a" * 300]
    for _ in range(40):
        own = [word() for _ in range(rng.randint(1, 120))]
        if rng.random() < 0.6:
            p = rng.choice(passages)
            cut = rng.randint(0, len(p) // 3)
            own.insert(rng.randint(0, len(own)), p[cut : len(p) - rng.randint(0, len(p) // 3)])
        texts.append(" ".join(own))
    base = [word() for _ in range(200)]
    for _ in range(12):
        near = list(base)
        for _ in range(4):
            near[rng.randrange(len(near))] = word()
        texts.append(" ".join(near))
    return texts + [texts[8], texts[9], texts[8], " ".join(base)]


@pytest.mark.parametrize(("hot", "bits"), [(10**9, 64), (3, 64), (5, 3)])
def test_cut_repeats_equals_brute_force(spark, hot, bits):
    texts = corpus()
    docs = spark.createDataFrame([(i, t, "x", f"n{i}") for i, t in enumerate(texts)], "doc_id long, text string, node string, kept string")
    got = {r.doc_id: tuple(r) for r in repeats.cut_repeats(docs, span=60, gram=12, hot_from=hot, with_text=True, carry=("node", "text"), hash_bits=bits).collect()}
    want = brute(texts, 60)
    assert {i: w for i, w in enumerate(want) if got[i][1:5] != w} == {}
    assert all(g[6] == "x" and g[7] == texts[i] for i, g in got.items())


def test_numbers_are_the_same_in_python_and_in_the_jvm(spark):
    texts = ["", "a", "é😀", "x" * 1000]
    rows = spark.createDataFrame([(t,) for t in texts], "text string").select("text", *(c.alias(n) for c, n in zip(repeats.text_key(repeats.F.col("text")), ("h1", "h2"), strict=True))).collect()
    for r in rows:
        assert repeats.node_of(r.text.encode(), {}) == r.h1
        assert repeats.node_of(r.text.encode(), {(r.h1, r.h2): 77}) == 77


def test_long_texts_go_in_pieces(monkeypatch):
    """Equal strings have their place at the same offset, wherever pieces begin."""
    rng = np.random.default_rng(0)
    data = rng.integers(97, 100, 5000).astype(np.uint8)
    data[3000:3700] = data[100:800]
    whole = repeats.anchors(data, 60, 12)
    monkeypatch.setattr(repeats, "PIECE", 333)
    for place, h, first, last in (whole, repeats.anchors(data, 60, 12)):
        assert sum((last - first + 1).tolist()) == len(data) - 59
        at = {s: (p - s, x) for p, x, f, e in zip(place.tolist(), h.tolist(), first.tolist(), last.tolist(), strict=True) for s in range(f, e + 1)}
        assert all(0 <= d <= 48 for d, _ in at.values()) and all(at[100 + i] == at[3000 + i] for i in range(640))


def test_empty_and_repeated_rows(spark):
    empty = spark.createDataFrame([], "doc_id long, text string")
    assert repeats.cut_repeats(empty).count() == 0
    rows = spark.createDataFrame([(1, "q" * 250), (1, "q" * 250), (None, "short"), (None, None)], "doc_id long, text string")
    assert sorted(tuple(r[1:4]) for r in repeats.cut_repeats(rows).collect()) == [(0, 0, 0), (5, 0, 0), (250, 250, 1), (250, 250, 1)]


def test_interval_tree_has_all_occurrences():
    groups, _, _ = repeats.maximal_repeats([b"xabcabcde", b"yabcabcdf", b"zabcabq"], 3)
    found = {(length, tuple(sorted(zip(w.tolist(), o.tolist())))) for length, w, o in groups}
    assert (7, ((0, 1), (1, 1))) in found
    assert (5, ((0, 1), (1, 1), (2, 1))) in found
    assert any(length == 3 and len(o) == 5 for length, o in found)


def test_intervals_nest():
    tree = repeats.intervals(np.array([0, 4, 6, 4, 2, 5]), 2)
    assert sorted(x[:3] for x in tree) == [(2, 0, 5), (4, 0, 3), (5, 4, 5), (6, 1, 2)]
    lengths = {i: x[0] for i, x in enumerate(tree)}
    assert all(x[3] == -1 or lengths[x[3]] < x[0] for x in tree)
