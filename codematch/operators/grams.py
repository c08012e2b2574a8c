"""Pairs of documents with nearly the same set of word grams, from sets that travel as packed numbers.

Of two sets with a Jaccard similarity of 7 / 10 the first grams of each in any common order, as many as it
may lack and one more, hold a common one. The order puts frequent grams last, as far as a list of bounded size
tells them, so only rare grams are dealt out; any order finds all pairs. Whole sets are then compared.
"""

from __future__ import annotations

from collections.abc import Callable, Iterator

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from codematch.operators.search import small
from codematch.sources.io import discard, materialize

#: A task names the grams that so many of its documents have; so many of the most frequent are listed.
FREQUENT, LISTED = 4, 1_000_000
#: Grams that a task packs before they leave it or that a bucket has, and pairs that a task holds before equal ones become one.
PACKED, HELD = 1 << 22, 1 << 21
_ROLE = (np.uint64(0x9E3779B97F4A7C15), np.uint64(0xC2B2AE3D27D4EB4F), np.uint64(0x165667B19E3779F9))


def _mix(x: np.ndarray, salt: int = 0) -> np.ndarray:
    x = x ^ np.uint64(salt)
    x = (x ^ x >> np.uint64(30)) * np.uint64(0xBF58476D1CE4E5B9)
    x = (x ^ x >> np.uint64(27)) * np.uint64(0x94D049BB133111EB)
    return x ^ x >> np.uint64(31)


def _flat(col: pa.Array, kind=np.uint64) -> tuple[np.ndarray, np.ndarray]:
    """(values of all rows, number of the row of each)."""
    size = np.nan_to_num(col.value_lengths().to_numpy(zero_copy_only=False)).astype(np.int64)
    return col.flatten().to_numpy(zero_copy_only=False).view(kind), np.repeat(np.arange(len(col)), size)


def gram_sets(texts: DataFrame, short: bool = False) -> DataFrame:
    """(id, s): the distinct 3-grams of the words of text as sorted 64-bit hashes; sets without any are absent.

    short: (id, n, one, two, s, sketch), with the number of grams, a digest of 128 bits, the first 32 bits of
    each hash in the same order, and a sketch for sketches_near.
    """
    words = F.filter(F.split(F.lower("text"), r"[^\p{L}\p{N}]+"), lambda w: w != "")
    rows = texts.select("id", F.transform(words, lambda w: F.xxhash64(w)).alias("w")).where(F.size("w") >= 3)

    def run(batches):
        for batch in batches:
            if not batch.num_rows:
                continue
            w, row = _flat(batch.column(1))
            at = np.flatnonzero(row[2:] == row[:-2])
            g, row = _mix(w[at] * _ROLE[0] + w[at + 1] * _ROLE[1] + w[at + 2] * _ROLE[2]), row[at]
            cuts = np.searchsorted(row, np.arange(batch.num_rows + 1))
            for lo, hi in zip(cuts[:-1], cuts[1:], strict=True):
                g[lo:hi].sort()
            new = np.r_[True, (g[1:] != g[:-1]) | (row[1:] != row[:-1])]
            g, row = g[new], row[new]
            n = np.bincount(row, minlength=batch.num_rows)
            start = np.r_[0, np.cumsum(n)]
            each = [g[lo:hi] for lo, hi in zip(start[:-1], start[1:], strict=True)]
            if not short:
                yield pa.RecordBatch.from_arrays([batch.column(0), pa.array([x.tobytes() for x in each], pa.binary())], names=["id", "s"])
                continue
            one, two = (np.add.reduceat(_mix(g, salt), start[:-1]).view(np.int64) for salt in (0x1234567, 0x7654321))
            s = pa.ListArray.from_arrays(pa.array(start, pa.int32()), pa.array((g >> np.uint64(32)).astype(np.uint32).view(np.int32)))
            sketches = pa.array([_sketch(x) for x in each], pa.binary())
            yield pa.RecordBatch.from_arrays([batch.column(0), pa.array(n), pa.array(one), pa.array(two), s, sketches], names=["id", "n", "one", "two", "s", "sketch"])

    return rows.mapInArrow(run, "id long, n long, one long, two long, s array<int>, sketch binary" if short else "id long, s binary")


def _sketch(g: np.ndarray) -> bytes:
    """The size of a set, and by the last bits of its hashes the parities of at least twice as many places."""
    width = max(64, 1 << (2 * len(g) - 1).bit_length())
    odd = np.bincount((g & np.uint64(width - 1)).astype(np.int64), minlength=width) & 1
    return len(g).to_bytes(8, "little") + np.packbits(odd.astype(np.uint8), bitorder="little").tobytes()


def sketches_near(x: bytes, y: bytes) -> bool:
    """False only if the similarity is under 7 / 10: each hash that one of two sets lacks changes one parity, so sets differ in as many or more."""
    n = int.from_bytes(x[:8], "little") + int.from_bytes(y[:8], "little")
    p, q = sorted((np.frombuffer(z, np.uint64, offset=8) for z in (x, y)), key=len)
    apart = p ^ np.bitwise_xor.reduce(q.reshape(-1, len(p)), axis=0)
    return 17 * int(np.bitwise_count(apart).sum()) <= 3 * n


def sets_near(x: bytes, y: bytes) -> bool:
    """Whether the similarity of two sets of sorted hashes is 7 / 10 or more."""
    p, q = np.frombuffer(x, np.uint64), np.frombuffer(y, np.uint64)
    at = np.searchsorted(p, q)
    at[at == len(p)] = 0
    c = int((p[at] == q).sum())
    return c * 10 >= 7 * (len(p) + len(q) - c)


def frequent_grams(sets: DataFrame) -> tuple[np.ndarray, np.ndarray]:
    """(g, n): grams that many sets of a task have, by rising g, and in how many sets of such tasks they are; at most LISTED, the most frequent.

    This only orders grams, so numbers need not be whole.
    """

    def count(batches):
        held, size = [], 0

        def frequent():
            g, n = np.unique(np.concatenate(held), return_counts=True)
            many = n >= FREQUENT
            return pa.RecordBatch.from_arrays([pa.array(g[many].astype(np.int64)), pa.array(n[many])], names=["g", "n"])

        for batch in batches:
            held.append(_flat(batch.column(0), np.uint32)[0])
            size += len(held[-1])
            if size >= PACKED:
                yield frequent()
                held, size = [], 0
        if size:
            yield frequent()

    total = sets.select("s").mapInArrow(count, "g long, n long").groupBy("g").agg(F.sum("n").alias("n"))
    found = total.orderBy(F.desc("n"), "g").limit(LISTED).toArrow()
    g, n = found.column("g").to_numpy().astype(np.uint32), found.column("n").to_numpy()
    order = np.argsort(g)
    return g[order], n[order]


def _bytes(batches: list[pa.RecordBatch], column: str, kind) -> np.ndarray:
    return np.concatenate([np.empty(0, kind), *(np.frombuffer(b, kind) for batch in batches for b in batch.column(column).to_pylist())])


def met_sets(sets: DataFrame, total: int) -> DataFrame:
    """(a, b), a < b, of sets(id, n, s) of short hashes that have a gram in common among those that each must share with a set like it; total is the number of grams."""
    buckets = max(24, -(-total * 3 // (10 * PACKED)))
    ranked = sets.sparkSession.sparkContext.broadcast(frequent_grams(sets))

    def packed(g, ids, n):
        bucket = g.astype(np.uint64) * np.uint64(buckets) >> np.uint64(32)
        order = np.argsort(bucket.astype(np.int32), kind="stable")
        g, ids, n = g[order], ids[order], n[order]
        cuts = np.searchsorted(bucket[order], np.arange(buckets + 1))
        out = []
        for b in np.flatnonzero(np.diff(cuts)):
            lo, hi = cuts[b], cuts[b + 1]
            run = np.flatnonzero(np.r_[True, ids[lo + 1 : hi] != ids[lo : hi - 1]])
            out.append((int(b), g[lo:hi].tobytes(), ids[lo:hi][run].tobytes(), n[lo:hi][run].astype(np.int32).tobytes(), np.diff(np.r_[run, hi - lo]).astype(np.int32).tobytes()))
        kinds = (pa.int32(), *[pa.binary()] * 4)
        return pa.RecordBatch.from_arrays([pa.array(c, k) for c, k in zip(zip(*out, strict=True), kinds, strict=True)], names=["bucket", "g", "id", "n", "times"])

    def first(batches):
        known, counts = ranked.value
        held, size = [], 0
        for batch in batches:
            if not batch.num_rows:
                continue
            g, row = _flat(batch.column(2), np.uint32)
            at = np.minimum(np.searchsorted(known, g), max(len(known) - 1, 0))
            rank = np.where(known[at] == g, counts[at], 0) if len(known) else np.zeros(len(g), np.int64)
            order = np.argsort(row * (int(rank.max(initial=0)) + 1) + rank, kind="stable")
            n = batch.column(1).to_numpy()
            start = np.r_[0, np.cumsum(n)][:-1]
            lead = order[np.arange(len(g)) - start[row] < (n - -(-7 * n // 10) + 1)[row]]
            held.append((g[lead], batch.column(0).to_numpy()[row[lead]], n[row[lead]]))
            size += len(lead)
            if size >= PACKED:
                yield packed(*(np.concatenate(x) for x in zip(*held, strict=True)))
                held, size = [], 0
        if size:
            yield packed(*(np.concatenate(x) for x in zip(*held, strict=True)))

    def distinct(found):
        p = np.concatenate(found)
        p = p[np.lexsort((p[:, 1], p[:, 0]))]
        return p[np.r_[True, (p[1:] != p[:-1]).any(1)]] if len(p) else p

    def rows(p):
        return pa.RecordBatch.from_arrays([pa.array(p[:, 0]), pa.array(p[:, 1])], names=["a", "b"])

    def meet(key: tuple[pa.Scalar, ...], batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        batches = list(batches)
        times = _bytes(batches, "times", np.int32)
        g, ids, n = _bytes(batches, "g", np.uint32), np.repeat(_bytes(batches, "id", np.int64), times), np.repeat(_bytes(batches, "n", np.int32), times)
        order = np.argsort(g)
        g, ids, n = g[order], ids[order], n[order].astype(np.int64)
        at, d, held, size = np.arange(len(g)), 1, [], 0
        while len(at):
            at = at[at + d < len(g)]
            at = at[g[at] == g[at + d]]
            for step in range(0, len(at), HELD):
                x = at[step : step + HELD]
                y = x + d
                near = (10 * n[x] >= 7 * n[y]) & (10 * n[y] >= 7 * n[x]) & (ids[x] != ids[y])
                x, y = ids[x[near]], ids[y[near]]
                held.append(np.c_[np.minimum(x, y), np.maximum(x, y)])
                size += len(x)
                if size > HELD:
                    held = [distinct(held)]
                    size = len(held[0])
                    if size > HELD // 2:
                        yield rows(held[0])
                        held, size = [], 0
            d += 1
        if size:
            yield rows(distinct(held))

    dealt = sets.select("id", "n", "s").mapInArrow(first, "bucket int, g binary, id binary, n binary, times binary").repartition(buckets, "bucket")
    return dealt.groupBy("bucket").applyInArrow(meet, "a long, b long").distinct()


def _compared(pairs: DataFrame, items: DataFrame, near: Callable[[bytes, bytes], bool]) -> DataFrame:
    """Of the pairs (a, b), a < b, those for which near(s of a, s of b) holds; items(id, s) may be more.

    Pairs go to the least neighbour of their first one, so that an item goes once to where a group of like ones is compared.
    """
    least = pairs.groupBy(F.col("b").alias("a")).agg(F.min("a").alias("home"))
    pairs = materialize(pairs.join(least, "a", "left").select(F.coalesce("home", "a").alias("home"), "a", "b"), "homes")
    ends = pairs.select("home", F.col("a").alias("id")).unionAll(pairs.select("home", "b")).distinct()
    sent = items.join(small(ends), "id").select("home", F.col("id").alias("a"), F.lit(None).cast("long").alias("b"), "s")
    spots = max(24, -(-pairs.count() // 20_000))
    rows = pairs.withColumn("s", F.lit(None).cast("binary")).unionAll(sent).withColumn("spot", F.pmod(F.xxhash64("home"), F.lit(spots)).cast("int"))

    def compare(key: tuple[pa.Scalar, ...], batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        asked, of = [], {}
        for batch in batches:
            for a, b, s in zip(*(batch.column(c).to_pylist() for c in ("a", "b", "s")), strict=True):
                if b is None:
                    of[a] = s
                else:
                    asked.append((a, b))
        kept = [p for p in asked if near(of[p[0]], of[p[1]])]
        yield pa.RecordBatch.from_arrays([pa.array([p[i] for p in kept], pa.int64()) for i in (0, 1)], names=["a", "b"])

    return rows.repartition(spots, "spot").groupBy("spot").applyInArrow(compare, "a long, b long")


def near_classes(texts: DataFrame) -> tuple[DataFrame, DataFrame]:
    """members (id, class) of texts(id, text) with the same grams, and pairs (a, b), a < b, of classes with a similarity of 7 / 10 or more; a class is its least id."""
    sets = materialize(gram_sets(texts, short=True), "gram-sets")
    least = sets.groupBy("one", "two").agg(F.min("id").alias("class"))
    members = materialize(sets.select("id", "one", "two").join(least, ["one", "two"]).select("id", "class"), "members")
    copies = members.where("id <> class").select("id")
    total = sets.agg(F.sum("n").alias("n")).first().n or 0
    met = materialize(met_sets(sets.join(small(copies), "id", "left_anti").select("id", "n", "s"), total), "met")
    like = materialize(_compared(met, sets.select("id", F.col("sketch").alias("s")), sketches_near), "like")
    discard(sets, met)
    asked = like.select(F.col("a").alias("id")).unionAll(like.select("b")).distinct()
    return members, materialize(_compared(like, gram_sets(texts.join(small(asked), "id", "left_semi")), sets_near), "near")
