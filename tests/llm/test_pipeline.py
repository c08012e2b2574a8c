"""The pipeline on a whole small table, stage by stage against plain code."""

import re

import corpus_pipeline as cp
from test_jaccard_join import brute as components
from test_repeats import brute as repeats


def words(text):
    return re.findall(r"[^\x00-\x2F\x3A-\x60\x7B-\x7F]+", re.sub("[A-Z]", lambda m: m[0].lower(), text))


def windows(text):
    w = words(text)
    n = min(len(w), 10)
    return {tuple(w[i : i + n]) for i in range(len(w) - n + 1)} if n else set()


def test_stages_equal_plain_code(spark, sf):
    docs = cp.read_table(spark, sf, "documents")
    rows = {r.doc_id: r for r in docs.collect()}
    kept = []
    for name, stage in cp.STAGES[:-1]:
        out = cp.materialize(stage(spark, docs, sf), "test")
        assert out.columns == cp.COLUMNS
        before, after = {r.doc_id: r.text for r in docs.collect()}, {r.doc_id: r.text for r in out.collect()}
        if name == "language ID":
            assert set(before) - set(after) <= {i for i, t in before.items() if len(t) < 40}
        elif name == "n-gram Jaccard join":
            want = components(sorted(before.items()))
            assert set(after) == {int(i) for i, n, c in want if n == 0 or i == c}
        elif name == "suffix-array dedup":
            ids = sorted(before)
            gone = {i: r[1] for i, r in zip(ids, repeats([before[i] for i in ids], 200), strict=True)}
            for i in ids:
                if gone[i] == 0:
                    assert after[i] == before[i]
                elif i in after:
                    assert len(before[i].encode()) - gone[i] - len(after[i].encode()) in range(0, 8)
                else:
                    assert len(before[i].encode()) - gone[i] < 8
        else:
            items = set().union(*(windows(r.text) for r in cp.read_table(spark, sf, "benchmark").collect()))
            short = {len(w) for w in items}
            hit = {i for i, t in before.items() if any(tuple(words(t)[j : j + n]) in items for n in short for j in range(len(words(t)) - n + 1))}
            assert set(after) == set(before) - hit
        docs = out
        kept.append(len(after))
    assert kept == sorted(kept, reverse=True) and kept[-1] > 0.6 * len(rows)
    packed = cp.STAGES[-1][1](spark, docs, sf).collect()
    assert sum(r.length for r in packed) == sum(len(r.text.split()) + 1 for r in docs.collect())


def test_an_id_on_several_texts_loses_only_the_copies(spark, sf):
    near = " ".join(f"w{i}" for i in range(60))
    rows = [(1, near), (2, near + " more"), (2, "another text of its own that nobody has " * 3), (3, near), (3, near), (None, near), (4, None), (4, "  "), (5, "lone words only")]
    rows += [(6, "one two three four five six"), (6, "one two three four five six"), (6, "seven eight nine ten eleven twelve")]
    docs = spark.createDataFrame([(i, t, "en", "s", 0) for i, t in rows], "doc_id long, text string, lang string, source string, n_chars long")
    out = cp.keep_one_of_near_copies(spark, docs, sf)
    want = [(1, near), rows[2], (None, near), (4, None), (4, "  "), (5, "lone words only"), rows[9], rows[11]]
    assert out.columns == cp.COLUMNS and sorted(repr((r.doc_id, r.text)) for r in out.collect()) == sorted(map(repr, want))
    assert cp.keep_one_of_near_copies(spark, docs.limit(0), sf).count() == 0
