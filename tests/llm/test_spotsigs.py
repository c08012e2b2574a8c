import hashlib
import itertools
import re

from codematch.llm import spotsigs


def spots(text):
    common = set(spotsigs.anchor_words())
    words = [w for w in re.split(r"[^\w]+|_", (text or "").lower()) if w]
    out = set()
    for i, w in enumerate(words):
        chain = [x for x in words[i + 1 :] if x not in common][:2]
        if w in common and len(chain) == 2:
            out.add((w, *chain))
    if not out:
        return {("words", " ".join(words))} if words else {("characters", text)} if text else set()
    return out


def jac(a, b):
    return 1.0 if not a and not b else len(a & b) / len(a | b)


TEXTS = [(5, "The cat of the house was seen by a dog in Rome"), (2, None), (3, ""), (9, "??? !!"), (4, "The cat of the house was seen by a dog in Rome"), (11, "der Hund ist ein Tier und die Katze auch"), (8, "x"), (4, "another text of the same number"), (None, "no number but the words are here")]


def test_edits_equal_brute_force(spark):
    docs = spark.createDataFrame([(i, t, "n") for i, t in TEXTS], "doc_id long, text string, next_text string")
    got = spotsigs.fingerprint_edits(docs).collect()
    assert len(got) == len(TEXTS)
    by = {}
    for r in got:
        by.setdefault(r.doc_id, []).append(r)
    order = sorted({i for i, _ in TEXTS if i is not None})
    texts = {i: t or "" for i, t in TEXTS}
    single = [i for i in order if i != 4]
    for i in single:
        follow = order[(order.index(i) + 1) % len(order)]
        if follow == 4 or i == order[-1]:
            continue
        t, u = texts[i], texts[follow]
        half = len(t) // 2
        edited = t[: len(t) - half] + u[:half]
        r = by[i][0]
        assert r.n_chars == len(t)
        assert r.edited_sha256 == hashlib.sha256(edited.encode()).hexdigest()
        assert abs(r.near_edited - jac(spots(t), spots(edited))) < 1e-12
        assert abs(r.near_next - jac(spots(t), spots(u))) < 1e-12
    last = by[11][0]  # followed by the row without a number, which comes first
    t, u = texts[11], TEXTS[-1][1]
    assert last.edited_sha256 == hashlib.sha256((t[: len(t) - len(t) // 2] + u[: len(t) // 2]).encode()).hexdigest()
    same = {r.fingerprint for r in by[4] + by[5] if r.n_chars == len(TEXTS[0][1])}
    assert len(same) == 1
    assert {r.fingerprint for i in (2, 3) for r in by[i]} == {""}


def test_order_over_many_ranges(spark, sf):
    docs = spark.read.parquet(f"{sf}/documents.parquet")
    got = {r.doc_id: r for r in spotsigs.fingerprint_edits(docs).collect()}
    rows = sorted(docs.select("doc_id", "text").collect())
    for (i, t), (_, u) in zip(rows, rows[1:] + rows[:1], strict=True):
        half = len(t) // 2
        assert got[i].edited_sha256 == hashlib.sha256((t[: len(t) - half] + u[:half]).encode()).hexdigest()


def test_empty_table(spark):
    assert spotsigs.fingerprint_edits(spark.createDataFrame([], "doc_id long, text string")).count() == 0


def test_pairs_equal_all_pairs(spark, sf):
    docs = spark.read.parquet(f"{sf}/documents.parquet").select("doc_id", "text")
    members, pairs = spotsigs.spot_pairs(docs)
    sets = {r.doc_id: spots(r.text) for r in docs.collect()}
    first = {}
    for i in sorted(sets):
        first.setdefault(frozenset(sets[i]), i)
    assert {r.doc_id: r["class"] for r in members.collect()} == {i: first[frozenset(s)] for i, s in sets.items()}
    reps = sorted(first.values())
    want = {(a, b) for a, b in itertools.combinations(reps, 2) if sets[a] and sets[b] and jac(sets[a], sets[b]) >= 0.75}
    assert {(r.a, r.b) for r in pairs.collect()} == want
