import random
import zlib

import numpy as np
import pytest
from pyspark.sql import functions as F

from codematch.llm import quality, toxicity


@pytest.mark.parametrize(("op", "label", "rest", "least"), [(toxicity, "toxic", 1, 0.93), (quality, "quality", 0, 0.97)])
def test_held_out_accuracy(spark, op, label, rest, least):
    d = "/root/testdata/sf0.01"
    docs, labels = spark.read.parquet(f"{d}/documents.parquet"), spark.read.parquet(f"{d}/labels.parquet")
    got = op.score_documents(docs, labels).toPandas()
    assert len(got) == docs.count() and got.score.between(0, 1).all()
    both = got.merge(labels.toPandas(), on="doc_id")
    both = both[both.held_out]
    assert len(both) > 40 and (both.predicted == both[label]).mean() >= least


@pytest.mark.parametrize("op", [toxicity, quality])
def test_odd_rows(spark, op):
    docs = spark.createDataFrame([(1, None, 0.5), (2, "", 0.5), (None, "a b c", 0.5), (2, "", 0.5), (3, "😀 é " * 40_000, 0.5)], "doc_id long, text string, score double")
    name = "toxic" if op is toxicity else "quality"
    labels = spark.createDataFrame([(1, 1), (1, 0), (None, 1), (2, None), (7, 0)], f"doc_id long, {name} int")
    for known in (labels, labels.limit(0)):
        got = op.score_documents(docs, known).collect()
        assert len(got) == 5 and all(0 <= r.score <= 1 and r.held_out is not None for r in got)
    assert op.score_documents(docs.limit(0), labels).count() == 0


def test_pairs_that_weights_alone_miss():
    rng = random.Random(4)
    rows, labels = [], []
    for _ in range(1500):
        insult, group = rng.random() < 0.5, rng.random() < 0.5
        own = {rng.randint(100, 140) for _ in range(6)} | ({1} if insult else {3}) | ({2} if group else {4})
        rows.append(np.array(sorted(own)))
        labels.append(float(insult == group))  # no term alone tells anything
    y = np.array(labels)
    terms = np.array([1, 2, 3, 4, *range(100, 141)])
    accuracy = lambda m: np.mean([(m.logit(np.searchsorted(terms, r)) > 0) == t for r, t in zip(rows, y, strict=True)])
    pairs, additive = toxicity.fit(rows, y, terms=terms), toxicity.fit(rows, y, terms=terms)
    additive.v = np.zeros_like(additive.v)
    assert accuracy(pairs) > 0.95
    assert accuracy(additive) < 0.7


def test_isotonic_and_kernel():
    x, v = quality.isotonic(np.arange(6.0), np.array([0, 1, 0, 1, 1, 0.0]), np.ones(6))
    assert (np.diff(v) >= 0).all() and abs(np.interp(1.5, x, v) - 0.5) < 1e-9
    f = quality.FourierFeatures(np.zeros(3), np.ones(3), n=20_000, width=1.5)
    a, b = np.array([[0.1, 0.2, 0.3]]), np.array([[0.4, -0.2, 0.0]])
    assert abs(float((f(a)[:, :-1] @ f(b)[:, :-1].T)[0, 0]) - np.exp(-((a - b) ** 2).sum() / (2 * 1.5**2))) < 0.03


def test_terms_that_tell_only_in_pairs_are_chosen():
    rng = random.Random(4)
    rows, labels = [], []
    for _ in range(1500):
        insult, group = rng.random() < 0.5, rng.random() < 0.5
        rows.append(np.array(sorted({rng.randint(100, 140) for _ in range(6)} | ({1} if insult else {3}) | ({2} if group else {4}))))
        labels.append(float(insult == group))
    y = np.array(labels)
    machine = toxicity.fit(rows, y)
    assert set(machine.terms) >= {1, 2, 3, 4}
    own = [np.flatnonzero(np.isin(machine.terms, r)) for r in rows]
    assert np.mean([(machine.logit(o) > 0) == t for o, t in zip(own, y, strict=True)]) > 0.95
    assert not len(toxicity.choose_terms(rows, np.array([float(rng.random() < 0.5) for _ in rows])))


def test_toxicity_equals_a_plain_machine(spark):
    """The same fit from plain rows, and every score by the sum over all pairs of terms."""
    d = "/root/testdata/sf0.001"
    docs, labels = spark.read.parquet(f"{d}/documents.parquet"), spark.read.parquet(f"{d}/labels.parquet")
    texts = {r.doc_id: r.text for r in docs.collect()}
    cache = toxicity.TermCache(int)
    known = {}
    for r in labels.collect():
        if r.toxic is not None and r.doc_id in texts and zlib.crc32(str(r.doc_id).encode()) % 3 != 1:
            own = np.array(sorted(toxicity.terms_of(texts[r.doc_id], cache)), np.int32).tobytes()
            known[own] = max(float(r.toxic), known.get(own, 0.0))
    rows = [np.frombuffer(k, np.int32).astype(np.int64) for k in sorted(known)]
    machine = toxicity.fit(rows, np.array([known[k] for k in sorted(known)]))
    place = {int(t): i for i, t in enumerate(machine.terms)}
    got = {r.doc_id: r for r in toxicity.score_documents(docs, labels).collect()}
    assert got.keys() == texts.keys()
    for i, text in texts.items():
        own = [place[t] for t in toxicity.terms_of(text, cache) if t in place]
        logit = machine.w0 + sum(machine.w[a] for a in own) + sum(float(machine.v[a] @ machine.v[b]) for n, a in enumerate(own) for b in own[n + 1 :])
        assert abs(got[i].score - 1 / (1 + np.exp(-np.clip(logit, -30, 30)))) < 1e-9
        assert got[i].predicted == (got[i].score >= 0.7) and got[i].held_out == (zlib.crc32(str(i).encode()) % 3 == 1)


def test_quality_equals_plain_ridge(spark):
    """The same weights and calibration from plain sums over all rows."""
    d = "/root/testdata/sf0.001"
    docs, labels = spark.read.parquet(f"{d}/documents.parquet"), spark.read.parquet(f"{d}/labels.parquet")
    rows = docs.select("doc_id", "text", (F.pmod(F.xxhash64("doc_id", F.lit("calibrate")), F.lit(5)) == 0).alias("later")).collect()
    label = {r.doc_id: float(r.quality) for r in labels.collect() if r.quality is not None}
    learnt = [r for r in rows if r.doc_id in label and zlib.crc32(str(r.doc_id).encode()) % 5 != 0]
    stats = {r.doc_id: np.array(quality.statistics(r.text.encode() if r.text else None)) for r in rows}
    x = np.array([stats[r.doc_id] for r in learnt if not r.later])
    y = np.array([label[r.doc_id] for r in learnt if not r.later])
    lift = quality.FourierFeatures(x.mean(0), x.std(0))
    z = lift(x)
    weights = np.linalg.solve(z.T @ z + quality.RIDGE * len(x) * np.eye(z.shape[1]), z.T @ y)
    raw = lambda i: float((lift(stats[i][None]) @ weights)[0])
    bins = {}
    for r in learnt:
        if r.later:
            v = raw(r.doc_id)
            bins.setdefault(np.floor(min(max(v, -0.5), 1.5) * quality.BINS / 2), []).append((v, label[r.doc_id]))
    means = [(np.mean([a for a, _ in b]), np.mean([t for _, t in b]), len(b)) for _, b in sorted(bins.items())]
    centres, values = quality.isotonic(*(np.array(c, float) for c in zip(*means, strict=True)))
    got = {r.doc_id: r for r in quality.score_documents(docs, labels).collect()}
    want = {i: float(np.clip(np.interp(raw(i), centres, values), 0, 1)) for i in stats}
    off = [i for i in want if abs(got[i].score - want[i]) > 1e-6]
    assert len(got) == len(want) and len(off) <= 0.01 * len(want)  # a raw score at the edge of a bin may fall to either side
