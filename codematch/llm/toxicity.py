"""Toxicity by a factorization machine over hashed terms.

A text is the set of its words, each hashed to one of BUCKETS terms. Terms that go with the
label clearly more or less often than chance, alone or together with another term, enter the
machine, with a weight and a vector each: the score is the logistic of the weights' sum and of
the products of all pairs of vectors, so a term may count only next to another one.

The machine is fitted on the driver, on at most SAMPLE labelled documents, those with the
smallest hashes; all documents are scored where they lie.
"""

from __future__ import annotations

import re
from dataclasses import dataclass

import numpy as np
import pyarrow as pa
import xxhash
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from codematch.llm.workers import released

BUCKETS = 1 << 20
SAMPLE, RANK = 20_000, 6
WORD = re.compile(r"[^\W\d_]+")


class TermCache(dict):
    LIMIT = 300_000

    def __init__(self, of):
        super().__init__()
        self.of = of

    def __missing__(self, word: str) -> int:
        if len(self) > self.LIMIT:
            self.clear()
        value = self[word] = self.of(xxhash.xxh3_64_intdigest(word.encode("utf-8", "surrogatepass")) % BUCKETS)
        return value


def terms_of(text: str | None, cache: TermCache) -> set[int]:
    return {cache[w] for w in set(WORD.findall(text.lower()))} if text else set()


@dataclass
class Machine:
    """terms: sorted buckets; w0, w and v: weights by term."""

    terms: np.ndarray
    w0: float
    w: np.ndarray
    v: np.ndarray

    def logit(self, own: np.ndarray) -> float:
        """own: places of a text's terms in self.terms."""
        v = self.v[own]
        s = v.sum(0)
        return float(self.w0 + self.w[own].sum() + 0.5 * (s * s - (v * v).sum(0)).sum())


def choose_terms(rows: list[np.ndarray], labels: np.ndarray, least_z: float = 4.5, least_rows: int = 4) -> np.ndarray:
    """The buckets whose share of label 1 is least_z standard errors from the overall share, and those of telling pairs."""
    base = float(np.clip(labels.mean(), 1e-6, 1 - 1e-6)) if len(labels) else 0.5
    if not rows or not sum(map(len, rows)):
        return np.empty(0, np.int64)
    flat, y = np.concatenate(rows), np.repeat(labels, [len(r) for r in rows])
    n, one = np.bincount(flat, minlength=BUCKETS), np.bincount(flat, weights=y, minlength=BUCKETS)
    z = np.abs(one - n * base) / np.sqrt(np.maximum(n, 1) * base * (1 - base))
    z[n < least_rows] = 0
    return np.union1d(np.flatnonzero(z >= least_z), pair_terms(flat, rows, labels, n, one, base, least_rows))


def pair_terms(flat: np.ndarray, rows: list[np.ndarray], labels: np.ndarray, n: np.ndarray, one: np.ndarray, base: float, least_rows: int, chance: float = 0.05) -> np.ndarray:
    """The buckets of pairs that say more together than either alone.

    The share of a label among texts with both terms must be above the shares of each term
    and of all texts, by a Chernoff bound that holds for all pairs of terms at once. That
    takes a least number of texts with both terms and the label, so only terms in so many
    are paired; texts of a term are a bit set.
    """
    vocabulary = int((n >= least_rows).sum())
    if vocabulary < 2:
        return np.empty(0, np.int64)
    bound = np.log(vocabulary * (vocabulary - 1.0) / chance)  # both labels of each pair
    text = np.repeat(np.arange(len(rows)), [len(r) for r in rows])
    telling = np.zeros(BUCKETS, bool)
    for label, share in ((1, base), (0, 1 - base)):
        of_label = one if label else n - one
        least = max(least_rows, int(np.ceil(bound / -np.log(share))))
        terms = np.flatnonzero((n >= least_rows) & (of_label >= least))
        if len(terms) < 2:
            continue
        bits = []
        for mine in (labels == label, labels != label):
            at = np.searchsorted(terms, flat)
            use = mine[text] & (terms[np.minimum(at, len(terms) - 1)] == flat)
            place = np.cumsum(mine) - 1
            words = np.zeros((int(mine.sum()) // 64 + 1, len(terms)), np.uint64)
            w = place[text[use]]
            np.bitwise_or.at(words, (w // 64, at[use]), np.uint64(1) << (w % 64).astype(np.uint64))
            bits.append(words)
        alone = np.maximum(of_label[terms] / n[terms], share)
        for i in range(len(terms) - 1):
            with_label = _common(bits[0], i, np.arange(i + 1, len(terms)))
            j = np.flatnonzero(with_label >= least)
            k = with_label[j]
            j = j + i + 1
            most = np.maximum(alone[i], alone[j])
            some = k * -np.log(np.minimum(most, 1 - 1e-12)) >= bound  # even if no other text had both
            j, k, most = j[some], k[some], most[some]
            if len(j):
                both = k + _common(bits[1], i, j)
                got = k / both
                rest = np.where(got < 1, (1 - got) * np.log(np.maximum(1 - got, 1e-300) / np.maximum(1 - most, 1e-12)), 0.0)
                sure = (got > most) & (both * (got * np.log(got / most) + rest) >= bound)
                if sure.any():
                    telling[terms[i]] = True
                    telling[terms[j[sure]]] = True
    return np.flatnonzero(telling)


def _common(words: np.ndarray, i: int, j: np.ndarray) -> np.ndarray:
    """How many bits column i has in common with each of the columns j."""
    at = np.flatnonzero(words[:, i])
    total = np.zeros(len(j), np.int64)
    run = slice(j[0], j[-1] + 1) if len(j) and j[-1] - j[0] + 1 == len(j) else j
    for w in at:
        total += np.bitwise_count(words[w, run] & words[w, i])
    return total


def fit(rows: list[np.ndarray], labels: np.ndarray, rank: int = RANK, rounds: int = 60, step: float = 0.15, decay: float = 2e-5, seed: int = 1, terms: np.ndarray | None = None) -> Machine:
    """Fits the machine to term sets and 0/1 labels by mini-batches with per-weight step sizes."""
    terms = choose_terms(rows, labels) if terms is None else terms
    rng = np.random.default_rng(seed)
    m = len(terms)
    share = float(np.clip(labels.mean() if len(labels) else 0.5, 1e-3, 1 - 1e-3))
    w0, w, v = np.log(share / (1 - share)), np.zeros(m), rng.normal(0, 0.05, (m, rank))
    g0, gw, gv = 1e-8, np.full(m, 1e-8), np.full((m, rank), 1e-8)
    own = []
    for r in rows:
        at = np.searchsorted(terms, r)
        own.append(at[(at < m) & (terms[np.minimum(at, m - 1)] == r)] if m else np.empty(0, np.int64))
    for _ in range(rounds if m else 0):
        order = rng.permutation(len(own))
        for i in range(0, len(order), 256):
            batch = order[i : i + 256]
            sizes = np.array([len(own[j]) for j in batch])
            flat, who = np.concatenate([own[j] for j in batch]), np.repeat(np.arange(len(batch)), sizes)
            vs = v[flat]
            total = np.zeros((len(batch), rank))
            np.add.at(total, who, vs)
            square = np.bincount(who, weights=(vs * vs).sum(1), minlength=len(batch))
            logit = w0 + np.bincount(who, weights=w[flat], minlength=len(batch)) + 0.5 * ((total**2).sum(1) - square)
            error = (1 / (1 + np.exp(-np.clip(logit, -30, 30))) - labels[batch]) / len(batch)
            dw = np.bincount(flat, weights=error[who], minlength=m) + decay * w
            dv = np.zeros((m, rank))
            np.add.at(dv, flat, error[who][:, None] * (total[who] - vs))
            dv += decay * v
            d0 = error.sum()
            g0, gw, gv = g0 + d0 * d0, gw + dw * dw, gv + dv * dv
            w0, w, v = w0 - step * d0 / np.sqrt(g0), w - step * dw / np.sqrt(gw), v - step * dv / np.sqrt(gv)
    return Machine(terms, float(w0), w, v)


def _features(batches):
    """(label, text) -> label and the sorted terms of the text."""
    cache = TermCache(int)
    schema = pa.schema([("label", pa.int32()), ("terms", pa.binary())])
    for batch in batches:
        for at in range(0, batch.num_rows, 256):
            part = batch.slice(at, 256)
            terms = [np.array(sorted(terms_of(t, cache)), np.int32).tobytes() for t in part.column(1).to_pylist()]
            yield pa.RecordBatch.from_arrays([part.column(0).cast(pa.int32()), pa.array(terms, pa.binary())], schema=schema)


def _scores(machine: Machine):
    def run(batches):
        at = {int(t): i for i, t in enumerate(machine.terms)}
        cache = TermCache(lambda b: at.get(b, -1))
        for batch in batches:
            for i in range(0, batch.num_rows, 256):
                part = batch.slice(i, 256)
                out = []
                for text in part.column(1).to_pylist():
                    own = np.array(sorted(terms_of(text, cache) - {-1}), np.int64)
                    out.append(1 / (1 + np.exp(-np.clip(machine.logit(own), -30, 30))))
                yield pa.RecordBatch.from_arrays([part.column(0), pa.array(out, pa.float64())], names=["doc_id", "score"])

    return run


def learn_rows(labels: DataFrame, label: str, held_out, sample: int) -> DataFrame:
    """(id, label) of at most `sample` labelled documents that are not held out, by the smallest hashes; an id that several rows label has the largest label."""
    known = labels.where(F.col("doc_id").isNotNull() & F.col(label).isNotNull() & ~held_out(F.col("doc_id"))).groupBy(F.col("doc_id").alias("labelled_id")).agg(F.max(F.col(label)).alias("label"))
    return known.orderBy(F.xxhash64("labelled_id"), "labelled_id").limit(sample)


def held_out(doc_id):
    return F.crc32(doc_id.cast("string")) % 3 == 1


def score_documents(docs: DataFrame, labels: DataFrame, sample: int = SAMPLE, threshold: float = 0.7) -> DataFrame:
    """One row per row of docs(doc_id BIGINT, text): doc_id, held_out, score, predicted.

    Learns from labels(doc_id, toxic) of rows that are not held out; without any, every score
    is 0.5. Null and empty texts get the score of a text without terms. A row without doc_id
    is scored and not held out. Repeated rows get a row each. Other columns are ignored.
    """
    docs = docs.select(F.col("doc_id").cast("long").alias("doc_id"), F.col("text").cast("string").alias("text"))
    some = learn_rows(labels, "toxic", held_out, sample)
    rows = docs.join(F.broadcast(some), F.col("doc_id") == F.col("labelled_id")).select("label", "text").mapInArrow(released(_features), "label int, terms binary").collect()
    distinct = {}  # copies count once
    for r in sorted(rows, key=lambda r: bytes(r.terms)):  # whatever the order of partitions
        distinct[bytes(r.terms)] = max(r.label, distinct.get(bytes(r.terms), 0))
    machine = fit([np.frombuffer(t, np.int32).astype(np.int64) for t in distinct], np.array(list(distinct.values()), float)) if distinct else Machine(np.empty(0, np.int64), 0.0, np.empty(0), np.empty((0, 1)))
    out = docs.mapInArrow(released(_scores(machine)), "doc_id long, score double")
    return out.select("doc_id", F.coalesce(held_out(F.col("doc_id")), F.lit(False)).alias("held_out"), "score", (F.col("score") >= threshold).cast("int").alias("predicted"))
