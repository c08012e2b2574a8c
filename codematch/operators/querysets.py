"""Search with large query sets: all sets at once, by joins on tokens."""

from __future__ import annotations

from collections.abc import Iterator

import numpy as np
import pyarrow as pa
from pyspark.sql import Column, DataFrame, Window
from pyspark.sql import functions as F

from codematch.operators.blocks import packed
from codematch.operators.search import top as best
from codematch.sources.io import materialize

POOLS = ("sum", "max", "maxfreq", "avg")


def pool(scores: DataFrame, how: str | Column = "sum") -> DataFrame:
    """(set_id, id, score) from (set_id, qid, id, score): items that no query of a set reached are absent, and add nothing.

    max takes the largest score; maxfreq multiplies it by log2(1 + number of queries that reached the item).
    """
    s = F.col("score")
    g = {"sum": F.sum(s), "max": F.max(s), "maxfreq": F.max(s) * F.log2(1 + F.count(F.lit(1)).cast("double")), "avg": F.avg(s)}[how] if isinstance(how, str) else how
    return scores.groupBy("set_id", "id").agg(g.cast("double").alias("score"))


def batch_search(q_tokens: DataFrame, d_tokens: DataFrame, top: int | None = None, min_hits: int = 1, preaggregate: bool = True, members: DataFrame | None = None) -> DataFrame:
    """(set_id, id, score): equal tokens of each set and item.

    q_tokens has (set_id, token) rows, one per query and position, and may have a weight w;
    d_tokens has (id, token). With preaggregate the equal tokens of a set are counted
    before the join, which gives the same sums from fewer joined rows. members (set_id, id)
    are left out of their own sets. With top, each set's best, ties by id, with rnk.
    """
    w = F.col("w") if "w" in q_tokens.columns else F.lit(1)
    q = q_tokens.groupBy("set_id", "token").agg(F.sum(w).alias("k")) if preaggregate else q_tokens.select("set_id", "token", w.alias("k"))
    out = q.join(d_tokens.select("id", "token"), "token").groupBy("set_id", "id").agg(F.sum("k").alias("score"))
    if min_hits > 1:
        out = out.where(F.col("score") >= min_hits)
    if members is not None:
        out = out.join(members, ["set_id", "id"], "left_anti")
    if top is None:
        return out
    return out.withColumn("rnk", F.row_number().over(Window.partitionBy("set_id").orderBy(F.desc("score"), "id"))).where(F.col("rnk") <= top)


def query_scores(q_tokens: DataFrame, d_tokens: DataFrame) -> DataFrame:
    """(set_id, qid, id, score): hits of each single query of a set, for pooling."""
    return q_tokens.join(d_tokens.select("id", "token"), "token").groupBy("set_id", "qid", "id").agg(F.count(F.lit(1)).cast("double").alias("score"))


#: Items of a block and sets of a group in recommend, members that a task packs before they leave it, and classes that a first bound is taken from.
ITEMS, SETS, PACKED, FIRST = 2_000_000, 60_000, 1 << 20, 64


class Items:
    """Items by equal codes, for the best of a set: a score is the sum of those of the two halves of a code.

    Different half codes are few at most, and fewer than items; of them only those are looked at that can still
    reach the score that enough items are known to have.
    """

    def __init__(self, ids: np.ndarray, coarse: np.ndarray, fine: np.ndarray):
        order = np.argsort(ids, kind="stable")
        self.ids, self.m, self.half = ids[order], fine.shape[1], fine.shape[1] // 2
        self.halves, self.words, at, tokens = [], [], [], 0
        for h in (0, 1):
            code = np.c_[coarse[order, h], fine[order, h * self.half : (h + 1) * self.half]].astype(np.int64)
            kinds, number = _numbered(code)
            quarters = []
            for lo, hi in ((1, 1 + self.half // 2), (1 + self.half // 2, 1 + self.half)):
                part, of = _numbered(kinds[:, [0, *range(lo, hi)]])
                places = []
                for p in range(1, part.shape[1]):
                    values, token = _numbered(part[:, [0, p]])
                    places.append(token + tokens)
                    self.words.append((_key(values[:, 0], values[:, 1]), tokens))
                    tokens += len(values)
                quarters.append((np.array(places, np.int64).reshape(-1, len(part)), of))
            self.halves.append(quarters)
            at.append(number)
        self.tokens = tokens
        kinds, self.kind = _numbered(np.c_[at[0], at[1]])
        self.one, self.two = kinds[:, 0], kinds[:, 1]
        self.start = np.searchsorted(self.one, np.arange(at[0].max(initial=-1) + 2))
        self.members = np.argsort(self.kind, kind="stable")
        self.left = np.bincount(self.kind, minlength=len(kinds))
        self.cut = np.r_[0, np.cumsum(self.left)]
        self.first = self.ids[self.members[self.cut[:-1]]]
        self.width = np.diff(self.start)

    def token_places(self, coarse: np.ndarray, fine: np.ndarray) -> np.ndarray:
        """(n, m): the places of the tokens of codes among those of all items; the last place for tokens that no item has."""
        out = np.empty(fine.shape, np.int32)
        for p, (keys, first) in enumerate(self.words):
            asked = _key(coarse[:, p // self.half], fine[:, p])
            at = np.minimum(np.searchsorted(keys, asked), len(keys) - 1)
            out[:, p] = np.where(keys[at] == asked, at + first, self.tokens)
        return out

    def best(self, count: np.ndarray, own: np.ndarray, top: int) -> tuple[np.ndarray, np.ndarray]:
        """(ids, scores) of the best by the number of each token, without the items at the places own; ties by id, none with 0."""
        a, b = ((count[t1].sum(0))[q1] + (count[t2].sum(0))[q2] for (t1, q1), (t2, q2) in self.halves)
        most = int(b.max())
        mine, times = np.unique(self.kind[own], return_counts=True)
        first = self.first[mine]
        self.left[mine] -= times
        extra = dict(zip(mine.tolist(), times.tolist(), strict=True))
        taken = set(own.tolist())
        lead = self.members[self.cut[mine]]
        for k in mine[np.isin(lead, own) & (self.left[mine] > 0)].tolist():
            self.first[k] = self.ids[next(r for r in self.members[self.cut[k] : self.cut[k] + extra[k] + 1].tolist() if r not in taken)]
        enough = np.cumsum(np.bincount(a, self.width)[::-1])
        least = max(0, len(enough) - 1 - int(np.searchsorted(enough, FIRST)))
        bound, reached = 1, None
        while True:
            some = np.flatnonzero(a >= least)
            size = self.width[some]
            kinds = np.arange(size.sum()) + np.repeat(self.start[some] - np.r_[0, np.cumsum(size)[:-1]], size)
            s = np.repeat(a[some], size) + b[self.two[kinds]]
            reached = np.cumsum(np.bincount(s, self.left[kinds])[::-1])
            at = int(np.searchsorted(reached, top))
            bound = max(1, len(reached) - 1 - at) if at < len(reached) else 1
            need = max(0, bound - most)
            if need >= least:
                break
            least = need
        keep = (s >= bound) & (self.left[kinds] > 0)
        kinds, s = kinds[keep], s[keep]
        tied = np.flatnonzero(s == bound)
        if len(tied) > top:
            near = tied[np.argpartition(self.first[kinds[tied]], top - 1)[:top]]
            chosen = np.r_[np.flatnonzero(s > bound), near]
            kinds, s = kinds[chosen], s[chosen]
        rows, scores = [], []
        for k, score in zip(kinds.tolist(), s.tolist(), strict=True):
            free = [r for r in self.members[self.cut[k] : min(self.cut[k + 1], self.cut[k] + top + extra.get(k, 0))].tolist() if r not in taken][:top]
            rows += free
            scores += [score] * len(free)
        self.left[mine] += times
        self.first[mine] = first
        rows, scores = np.array(rows, np.int64), np.array(scores, np.int64)
        chosen = np.lexsort((rows, -scores))[:top]
        return self.ids[rows[chosen]], scores[chosen]


def _key(coarse: np.ndarray, fine: np.ndarray) -> np.ndarray:
    return coarse.astype(np.int64) << 16 | fine


def _numbered(rows: np.ndarray) -> tuple[np.ndarray, np.ndarray]:
    """(different rows in order, the number of each row's)."""
    order = np.lexsort(rows.T[::-1])
    put = rows[order]
    new = np.r_[True, (put[1:] != put[:-1]).any(1)][: len(put)]
    number = np.empty(len(rows), np.int64)
    number[order] = np.cumsum(new) - 1
    return put[new], number



_ARROW = pa.schema([("g", pa.int32()), ("b", pa.int32()), *((c, pa.binary()) for c in ("set_id", "id", "coarse", "fine"))])
_PACKED = "g int, b int, set_id binary, id binary, coarse binary, fine binary"


def _codes(batch: pa.RecordBatch, m: int) -> tuple[np.ndarray, np.ndarray]:
    """(coarse (n, 2), fine (n, m)) of columns c1, c2, f0 and f1."""
    coarse = np.c_[batch.column("c1").to_numpy(), batch.column("c2").to_numpy()].astype(np.int32)
    fine = [batch.column(c).to_numpy().astype("<i8").reshape(-1, 1).view(np.uint8)[:, : m // 2] for c in ("f0", "f1")]
    return coarse, np.concatenate(fine, 1)


def recommend(members: DataFrame, codes: DataFrame, m: int, top: int, sets: int | None = None) -> DataFrame:
    """(set_id, id, score, rnk) as batch_search gives with these members as queries and left out, where each set reaches most items.

    members has (set_id, id), codes (id, c1, c2, fine). Sets are dealt over groups and items over blocks, both
    packed; a group meets each block, and for each of its sets the best items of the block are found (Items). sets is about how many sets
    there are, which the number of groups follows; without it they are counted. Scores of 0 don't come out.
    """
    own = materialize(packed(codes, m, "id"), "items")
    n = max(1, -(-own.count() // ITEMS))
    members = members.where("set_id IS NOT NULL AND id IS NOT NULL").select("set_id", "id")
    if sets is None:
        members = materialize(members, "members")
        sets = members.select("set_id").distinct().count()
    groups = max(12, -(-sets // SETS))
    each = lambda k: F.explode(F.sequence(F.lit(0), F.lit(k - 1)))
    members = members.withColumn("g", F.pmod(F.xxhash64("set_id"), F.lit(groups)).cast("int"))
    if n > 1:
        members = members.join(own, "id").select("g", "set_id", "id", "c1", "c2", "f0", "f1")
    else:
        members = members.select("g", "set_id", "id")
    items = own.select(F.pmod(F.xxhash64("id"), F.lit(n)).cast("int").alias("b"), "id", "c1", "c2", "f0", "f1")

    def pack(batches, by):
        held, size = [], 0

        def parts():
            table = pa.Table.from_batches(held).combine_chunks()
            number = table.column(by).to_numpy()
            for k in np.unique(number):
                part = table.take(pa.array(np.flatnonzero(number == k)))
                coarse, fine = _codes(part, m) if "c1" in part.column_names else (b"", b"")
                column = lambda c: part.column(c).to_numpy().astype(np.int64).tobytes()  # noqa: E731, B023
                row = {"g": None, "b": None, "set_id": column("set_id") if by == "g" else None, "id": column("id"), "coarse": bytes(np.ascontiguousarray(coarse)), "fine": bytes(np.ascontiguousarray(fine))} | {by: int(k)}
                yield pa.RecordBatch.from_pylist([row], _ARROW)

        for batch in batches:
            if batch.num_rows:
                held.append(batch)
                size += batch.num_rows
            if size >= PACKED:
                yield from parts()
                held, size = [], 0
        if size:
            yield from parts()

    rest = ["set_id", "id", "coarse", "fine"]
    asked = members.mapInArrow(lambda b: pack(b, "g"), _PACKED).select("g", each(n).alias("b"), *rest)
    known = items.mapInArrow(lambda b: pack(b, "b"), _PACKED).select(each(groups).alias("g"), "b", *rest)
    rows = asked.unionByName(known).repartition(n * groups, "g", "b")

    def run(key: tuple[pa.Scalar, ...], batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        queries, block = [], []
        for batch in batches:
            for row in zip(*(batch.column(c).to_pylist() for c in rest), strict=True):
                (block if row[0] is None else queries).append(row)
        if not queries or not block:
            return
        joined = lambda rows, i, kind, width: np.frombuffer(b"".join(r[i] for r in rows), kind).reshape(-1, width)
        ids, coarse, fine = joined(block, 1, np.int64, 1)[:, 0], joined(block, 2, np.int32, 2), joined(block, 3, np.uint8, m)
        order = np.argsort(ids, kind="stable")
        ids, coarse, fine = ids[order], coarse[order], fine[order]
        block = Items(ids, coarse, fine)
        number, member = (joined(queries, i, np.int64, 1)[:, 0] for i in (0, 1))
        order = np.lexsort((member, number))
        order = order[np.r_[True, (number[order][1:] != number[order][:-1]) | (member[order][1:] != member[order][:-1])]]
        if n > 1:
            places = block.token_places(joined(queries, 2, np.int32, 2)[order], joined(queries, 3, np.uint8, m)[order])
        number, member = number[order], member[order]
        at = np.minimum(np.searchsorted(ids, member), len(ids) - 1)
        here = ids[at] == member
        if n == 1:
            number, at, here = number[here], at[here], here[here]
            known = block.token_places(coarse, fine)
        cuts = np.flatnonzero(np.r_[True, number[1:] != number[:-1], True]) if len(number) else np.zeros(1, np.int64)
        out, size = [], 0
        for lo, hi in zip(cuts[:-1].tolist(), cuts[1:].tolist(), strict=True):
            tokens = known[at[lo:hi]] if n == 1 else places[lo:hi]
            found, score = block.best(np.bincount(tokens.ravel(), minlength=block.tokens + 1), at[lo:hi][here[lo:hi]], top)
            out.append((np.full(len(found), number[lo]), found, score, np.arange(1, len(found) + 1)))
            size += len(found)
            if size > 100_000 or hi == cuts[-1]:
                yield pa.RecordBatch.from_arrays([pa.array(np.concatenate(c), k) for c, k in zip(zip(*out, strict=True), (pa.int64(), pa.int64(), pa.int64(), pa.int32()), strict=True)], names=["set_id", "id", "score", "rnk"])
                out, size = [], 0

    met = rows.groupBy("g", "b").applyInArrow(run, "set_id long, id long, score long, rnk int")
    return met if n == 1 else best(met.drop("rnk"), top, "set_id")
