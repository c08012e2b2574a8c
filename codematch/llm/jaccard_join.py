"""N-gram Jaccard join by parity sketches.

A set is cut, by the high bits of its hashes, into parts; each part keeps the XOR of its
hashes, 64 parity bits. An element in which two sets differ spoils one part at most, so sets
whose symmetric difference is at most D differ in at most D parts: of the non-empty parts of
each, put in one order that all sets share, the first D + 1 hold a common one (pigeonhole).
D follows from the size and the least similarity. The number of parts is fixed per band of
sizes; a set joins its own band, and the next one if a partner can be there. A second sketch
of one parity bit an element bounds the symmetric difference from below and drops pairs
before the exact check, which compares whole shingle sets of whole texts.

Skew. Equal sets are one class from the start. The shared order puts parts that many sets
have last; it is a bounded list that only steers the order, never the result. Keys with more
than SMALL members make no pairs. Those of them that have their least member (numbers are hashes) and about
their size in common become one group, as the many keys of one shared passage do. The members
of a group are tied to that least member, and these ties are checked (a member's first TIES of
them). Of the groups that are still in several components, those of up to MEET members are sent
whole to a task each, which compares all their pairs by sketches. Members of larger ones are compared
with PIVOTS others of the group, and a member's first TIES near ones are checked; this is done
TURNS times with other pivots. What is left of these in different components meets in pairs, by a join
that ranges of size bound and whose rows are only pairs with near sketches. A large group is
dealt over blocks of its members there, and a set with many partners over salts when texts are
fetched.
Keys known as very frequent are dealt over several tasks.

Sets are known by a 64-bit digest. Where two different sets share one, which a second digest
shows, all but one of them get another number, so identity is by 128 bits.
"""

from __future__ import annotations

from collections.abc import Iterator
from functools import reduce

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame, Window
from pyspark.sql import functions as F

from codematch.functions.arrays import text_key
from codematch.llm.shingles import WordHashes, mix, set_digest, shingle_set
from codematch.llm.workers import released
from codematch.operators.graph import local_components
from codematch.operators.graph_components import star_components
from codematch.sources.io import discard, materialize

#: Sets under FIRST are their own parts; above, each band spans a factor of SPAN.
FIRST, SPAN = 32, 4
SMALL = 8
#: Tiers of sizes for the join of torn groups: (smallest size above the tier, 64-bit words of its sketches).
#: Sketches with about a bit an element tell most pairs apart.
TIERS = ((1024, 16), (4096, 64), (12288, 128), (1 << 62, 256))
#: Sketches of so many words are compared as columns of their own, wider ones as arrays.
COLUMNS = 64
#: Ties of a member that are checked first.
TIES = 4
#: A torn group of so many members or fewer is compared whole in one task.
MEET = 64
#: Pivots of a torn group in a turn, and turns before its members meet in pairs; pivots are broadcast up to a number of rows.
PIVOTS, TURNS, BROADCAST_PIVOTS = 64, 2, 100_000
#: Bound of the list of frequent keys; a task reports keys that it met so often among WINDOW_KEYS of them.
FREQUENT, REPORTED, WINDOW_KEYS = 200_000, 2, 2_000_000
#: Members of a torn group that meet those of one other block in a task.
BLOCK = 1024
#: Pairs of a set whose text goes to one task when they are verified.
PARTNERS = 256
#: Keys with so many sets or more are dealt over as many buckets as their number asks for, so many to each.
HOT = 200_000
#: Links up to this many are joined to components in one task; more by star contractions. Both give the same components.
LOCAL_LINKS = 200_000
#: Broadcast a list of ids only up to this many.
BROADCAST_IDS = 500_000


def band_of(n: int) -> tuple[int, int]:
    """(band, smallest size above it)."""
    band, top = 0, FIRST
    while n >= top:
        band, top = band + 1, top * SPAN
    return band, top


def parities(s: np.ndarray, band: int, top: int) -> np.ndarray:
    """One key for each non-empty part of the sorted set s under the band's partition."""
    if band == 0:
        return mix(s, 0xB0)
    part = ((s >> np.uint64(32)) * np.uint64(top)) >> np.uint64(32)
    at = np.flatnonzero(np.r_[True, part[1:] != part[:-1]])
    return mix(np.bitwise_xor.reduceat(s, at) ^ mix(part[at]), 0xB0 + band)


def bands(n: int, percent: int) -> list[tuple[int, int, int]]:
    """(band, top, keys needed) of each band in which a set of n elements has to be found."""
    most = 100 * n // percent
    slack = lambda other: (100 - percent) * (n + other) // (100 + percent)
    band, top = band_of(n)
    out = [(band, top, slack(min(top - 1, most)) + 1)]
    if most >= top:
        out.append((band + 1, top * SPAN, slack(most) + 1))
    return out


def tiers(n: int, percent: int) -> list[int]:
    """Tiers in which a set of n elements can be one of a pair whose larger set belongs there."""
    return [i for i, (top, _) in enumerate(TIERS) if n < top and 100 * n // percent >= (TIERS[i - 1][0] if i else 0)]


def bit_sketch(s: np.ndarray, percent: int = 75) -> bytes:
    """One parity bit an element; bits: a power of two, no fewer than elements or than the set's tiers compare."""
    bits = max(64 * TIERS[tiers(len(s), percent)[-1]][1], 1 << (len(s) - 1).bit_length())
    places = ((s & np.uint64(0xFFFFFFFF)) * np.uint64(bits)) >> np.uint64(32)
    return np.packbits((np.bincount(places.astype(np.int64), minlength=bits) & 1).astype(np.uint8)).tobytes()


def folded(sketch: bytes, words: int) -> np.ndarray:
    """A sketch brought to so many 64-bit words."""
    if len(sketch) > 8 * words:
        bits = np.unpackbits(np.frombuffer(sketch, np.uint8)).reshape(64 * words, -1).sum(1) & 1
        sketch = np.packbits(bits.astype(np.uint8)).tobytes()
    return np.frombuffer(sketch, np.int64)


def sketch_distance(a: bytes, b: bytes) -> int:
    """Hamming distance of two bit sketches; the longer is folded to the shorter's length (each place is a prefix of the finer one)."""
    x, y = (np.unpackbits(np.frombuffer(z, np.uint8)) for z in (a, b))
    if len(x) < len(y):
        x, y = y, x
    if len(x) > len(y):
        x = x.reshape(len(y), -1).sum(1) & 1
    return int((x != y).sum())


def _signed(x: np.ndarray) -> np.ndarray:
    return x.astype(np.uint64).view(np.int64)


def _rows(batch: pa.RecordBatch, size: int = 512) -> Iterator[tuple]:
    """Rows with the last column, a text, as bytes; few at a time."""
    for at in range(0, batch.num_rows, size):
        part = batch.slice(at, size)
        cols = [part.column(i) for i in range(part.num_columns)]
        cols[-1] = cols[-1].cast(pa.binary())
        yield from zip(*(c.to_pylist() for c in cols), strict=True)


def known_as(digests: tuple[int, int], other: dict, bits: int = 64) -> int:
    """The number of a set: its first digest, or what `other` has for both digests."""
    node, check = digests
    return other.get((cut_digest(node, bits), check), cut_digest(node, bits)) if other or bits < 64 else node


def cut_digest(node: int, bits: int) -> int:
    """The digest itself; tests cut it to a few bits, so that different sets share one."""
    return node if bits >= 64 else node & ((1 << bits) - 1)


def _describe(width: int, percent: int, bits: int = 64):
    """First pass over (doc_id, h1, h2, text): n, node, check and sketch of each text; frequent keys as rows with node = key, n = count, kind 1."""

    def frequent(keys):
        """keys are sorted where they are; only those that occur REPORTED times or more are copied."""
        keys.sort()
        twice = np.flatnonzero(keys[REPORTED - 1 :] == keys[: len(keys) - REPORTED + 1])
        value, count = np.unique(keys[twice], return_counts=True)
        m = len(value)
        columns = {"kind": pa.array(np.ones(m, np.int32)), "n": pa.array((count + REPORTED - 1).astype(np.int64)), "node": pa.array(_signed(value))}
        return pa.RecordBatch.from_arrays([columns.get(f.name, pa.nulls(m, f.type)) for f in _DESCRIBED], schema=_DESCRIBED)

    def run(batches):
        cache, keys, kept, seen = WordHashes(), np.empty(WINDOW_KEYS, np.uint64), 0, set()
        for batch in batches:
            out = []
            for doc, h1, h2, text in _rows(batch):
                s = shingle_set(text, width, cache)
                node, check = set_digest(s)
                node = cut_digest(node, bits)
                out.append((0, doc, h1, h2, len(s), node, check, bit_sketch(s, percent) if len(s) else None))
                if len(s) and (node, check) not in seen:
                    seen.add((node, check))
                    for band, top, _ in bands(len(s), percent):
                        own = parities(s, band, top)
                        for at in range(0, len(own), WINDOW_KEYS):
                            part = own[at : at + WINDOW_KEYS]
                            if kept + len(part) > WINDOW_KEYS:
                                yield frequent(keys[:kept])
                                kept = 0
                            keys[kept : kept + len(part)] = part
                            kept += len(part)
            if len(seen) > 100_000:
                seen.clear()
            if out:
                yield pa.RecordBatch.from_arrays([pa.array(c, f.type) for c, f in zip(zip(*out, strict=True), _DESCRIBED, strict=True)], schema=_DESCRIBED)
        if kept:
            yield frequent(keys[:kept])

    return run


_DESCRIBED = pa.schema(
    [("kind", pa.int32()), ("doc_id", pa.int64()), ("h1", pa.int64()), ("h2", pa.int64()), ("n", pa.int64()), ("node", pa.int64()), ("check", pa.int64()), ("sketch", pa.binary())]
)
_PACKED = pa.schema([("bucket", pa.int32()), ("keys", pa.binary()), ("nodes", pa.binary()), ("sizes", pa.binary())])
_GROUPS = pa.schema([("kind", pa.int32()), ("key", pa.int64()), ("a", pa.int64()), ("b", pa.int64()), ("n", pa.int64())])


def choose(keys: np.ndarray, need: int, ranked: tuple[np.ndarray, np.ndarray]) -> np.ndarray:
    """The first `need` keys in the order all sets share: by value, listed frequent ones after all others by rank."""
    if len(keys) <= need:
        return keys
    listed, rank = ranked
    if len(listed):
        at = np.minimum(np.searchsorted(listed, keys), len(listed) - 1)
        hit = listed[at] == keys
        if hit.any():
            rest = keys[~hit]
            if len(rest) >= need:
                keys = rest
            else:
                last = keys[hit]
                return np.r_[rest, last[np.argsort(rank[at[hit]], kind="stable")][: need - len(rest)]]
    return np.partition(keys, need - 1)[:need] if len(keys) > need else keys


def _emit(width: int, percent: int, buckets: int, ranked, hot, other: dict, bits: int = 64):
    """Second pass: the chosen keys of each set, packed by bucket: a row holds many."""

    def run(batches):
        cache = WordHashes()
        frequent, (very, salts) = ranked.value, hot.value
        keys, nodes, sizes, kept = [], [], [], 0

        def pack():
            each = [len(x) for x in keys]
            k, v, n = np.concatenate(keys), np.repeat(np.array(nodes, np.int64), each), np.repeat(np.array(sizes, np.int32), each)
            to = (k % np.uint64(buckets)).astype(np.int64)
            if len(very):
                at = np.minimum(np.searchsorted(very, k), len(very) - 1)
                split = very[at] == k
                to[split] = (to[split] + 1 + v[split] % salts[at[split]]) % buckets
            order = np.argsort(to, kind="stable")
            k, v, n, to = k[order], v[order], n[order], to[order]
            at = np.flatnonzero(np.r_[True, to[1:] != to[:-1]])
            ends = np.r_[at[1:], len(to)]
            packs = (pa.array([x[i:j].tobytes() for i, j in zip(at, ends, strict=True)], pa.binary()) for x in (k, v, n))
            return pa.RecordBatch.from_arrays([pa.array(to[at].astype(np.int32)), *packs], schema=_PACKED)

        seen: set[int] = set()
        for batch in batches:
            for (text,) in _rows(batch):
                s = shingle_set(text, width, cache)
                if not len(s):
                    continue
                node = known_as(set_digest(s), other, bits)
                if node in seen:
                    continue
                seen.add(node)
                for band, top, need in bands(len(s), percent):
                    keys.append(choose(parities(s, band, top), need, frequent))
                    nodes.append(node)
                    sizes.append(len(s))
                    kept += len(keys[-1])
                if kept > 400_000:
                    yield pack()
                    keys, nodes, sizes, kept = [], [], [], 0
            if len(seen) > 200_000:
                seen.clear()
        if kept:
            yield pack()

    return run


def _group(percent: int, hot):
    """Sets that share a key: pairs of small groups, members of large ones."""

    def run(batches):
        by: dict[int, list] = {}
        for batch in batches:
            for to, *cols in zip(*(batch.column(i).to_pylist() for i in range(4)), strict=True):
                by.setdefault(to, []).append([np.frombuffer(x, t) for x, t in zip(cols, (np.uint64, np.int64, np.int32), strict=True)])
        very, _ = hot.value
        for to in list(by):
            k, v, n = (np.concatenate(x) for x in zip(*by.pop(to), strict=True))
            order = np.lexsort((v, k))
            k, v, n = k[order], v[order], n[order]
            new = np.r_[True, (k[1:] != k[:-1]) | (v[1:] != v[:-1])]
            k, v, n = k[new], v[new], n[new]
            at = np.flatnonzero(np.r_[True, k[1:] != k[:-1]])
            many = np.diff(np.r_[at, len(k)])
            large = many > SMALL
            if len(very):
                large |= very[np.minimum(np.searchsorted(very, k[at]), len(very) - 1)] == k[at]
            member = np.repeat(large, many)
            pairs = []
            for gap in range(1, SMALL):
                first = np.flatnonzero((k[:-gap] == k[gap:]) & ~member[:-gap]) if len(k) > gap else np.empty(0, np.int64)
                second = first + gap
                fit = (np.minimum(n[first], n[second]).astype(np.int64) * 100 >= np.maximum(n[first], n[second]).astype(np.int64) * percent)
                pairs.append(np.c_[v[first[fit]], v[second[fit]]])
            p = np.concatenate(pairs)
            if len(p):
                p = p[np.lexsort((p[:, 1], p[:, 0]))]
                p = p[np.r_[True, (p[1:] != p[:-1]).any(1)]]
                yield pa.RecordBatch.from_pydict({"kind": [0] * len(p), "key": [None] * len(p), "a": p[:, 0], "b": p[:, 1], "n": [None] * len(p)}, _GROUPS)
            m = int(member.sum())
            if m:
                key, a, size = _homes(k, v, n, at, many, large, very)
                m = len(key)
                own = {"kind": [1] * m, "key": key, "a": a, "b": [None] * m, "n": size}
                yield pa.RecordBatch.from_pydict(own, _GROUPS)

    return run


def _homes(k, v, n, at, many, large, very) -> tuple[np.ndarray, np.ndarray, np.ndarray]:
    """(key, node, n) of the large groups of a bucket, where keys of one pivot and about one size are one group, as in _merged.

    k and v are sorted, so the pivot, the least member, is first. Keys that are dealt over buckets are not whole here and stay.
    """
    home = mix(v[at].view(np.uint64) ^ mix(np.log2(many).astype(np.uint64), 0xD1), 0xD2)
    if len(very):
        dealt = very[np.minimum(np.searchsorted(very, k[at]), len(very) - 1)] == k[at]
        home[dealt] = k[at][dealt]
    member = np.repeat(large, many)
    key, node, size = np.repeat(home, many)[member], v[member], n[member]
    order = np.lexsort((node, key))
    key, node, size = key[order], node[order], size[order]
    new = np.r_[True, (key[1:] != key[:-1]) | (node[1:] != node[:-1])]
    return _signed(key[new]), node[new], size[new].astype(np.int64)


def _folded(words: int):
    """(node, sketch) with the sketch as columns q0, q1 and so on, or as one array q."""
    columns = words <= COLUMNS

    def run(batches):
        for batch in batches:
            if batch.num_rows:
                q = np.array([folded(x, words) for x in batch.column(1).to_pylist()])
                if columns:
                    names = ["node", *(f"q{i}" for i in range(words))]
                    yield pa.RecordBatch.from_arrays([batch.column(0), *(pa.array(q[:, i]) for i in range(words))], names=names)
                else:
                    lists = pa.ListArray.from_arrays(pa.array(np.arange(len(q) + 1, dtype=np.int32) * words), pa.array(q.ravel()))
                    yield pa.RecordBatch.from_arrays([batch.column(0), lists], names=["node", "q"])

    return run


def _merged(member: DataFrame) -> DataFrame:
    """(key, pivot, node, n) of groups of keys: those with one least member, the pivot, and one size up to a factor of two.

    Sets that share a key share its group, so nothing is lost; the pivot shares a key with each.
    """
    per = member.groupBy("key").agg(F.min("node").alias("pivot"), F.floor(F.log2(F.count(F.lit(1)).cast("double"))).alias("wide"))
    home = per.select("key", "pivot", F.xxhash64("pivot", "wide").alias("home"))
    return member.join(home, "key").select(F.col("home").alias("key"), "pivot", "node", "n").distinct()


def _pivot_ties(rest: DataFrame, coarse: DataFrame, percent: int, turn: int) -> DataFrame:
    """(a, b): members of torn groups and pivots of other components whose sizes and small sketches are near; a member's first TIES.

    Each turn has other pivots.
    """
    w = Window.partitionBy("key").orderBy(F.xxhash64(F.lit(turn), "node"), "node")
    pivots = rest.withColumn("r", F.row_number().over(w)).where(F.col("r") <= PIVOTS).join(coarse, "node")
    pivots = pivots.select("key", "q", *(F.col(c).alias(f"{c}_p") for c in ("node", "part", "n")))
    pivots = materialize(pivots.withColumnRenamed("q", "q_p"), "pivots")
    few = F.broadcast(pivots) if pivots.count() <= BROADCAST_PIVOTS else pivots
    apart = " + ".join(f"bit_count(q.q{i} ^ q_p.q{i})" for i in range(TIERS[0][1]))
    sizes = f"n * 100 >= n_p * {percent} AND n_p * 100 >= n * {percent}"
    near = f"part <> part_p AND {sizes} AND ({apart}) * {100 + percent} <= (n + n_p) * {100 - percent}"
    own = rest.join(coarse, "node").select(F.col("key").alias("own_key"), "node", "part", "n", "q")
    met = own.join(few, F.expr(f"own_key = key AND {near}"))
    ties = materialize(_first_ties(met.select(F.col("node").alias("own"), F.col("node_p").alias("other")).distinct()), "ties")
    discard(pivots)
    return ties


def _near_in_group(percent: int):
    """(a, b) of one torn group (key, node, part, n, sketch): pairs of different components whose sizes and sketches are near."""

    def run(table: pa.Table) -> pa.Table:
        node, part, n = (table.column(c).to_numpy() for c in ("node", "part", "n"))
        sketch = table.column("sketch").to_pylist()
        x, y = np.triu_indices(len(node), 1)
        fit = (part[x] != part[y]) & (np.minimum(n[x], n[y]) * 100 >= np.maximum(n[x], n[y]) * percent)
        x, y = x[fit], y[fit]
        words = np.array([len(q) // 8 for q in sketch])
        both = np.minimum(words[x], words[y])
        near = np.zeros(len(x), bool)
        for width in np.unique(both):
            at = np.flatnonzero(both == width)
            own, place = np.unique(np.r_[x[at], y[at]], return_inverse=True)
            q = np.array([folded(sketch[i], int(width)) for i in own]).view(np.uint64)
            for some in np.array_split(np.arange(len(at)), len(at) * int(width) // 1_000_000 + 1):
                apart = np.bitwise_count(q[place[some]] ^ q[place[len(at) + some]]).sum(1, dtype=np.int64)
                near[at[some]] = apart * (100 + percent) <= (n[x[at[some]]] + n[y[at[some]]]) * (100 - percent)
        a, b = node[x[near]], node[y[near]]
        return pa.table({"a": pa.array(np.minimum(a, b), pa.int64()), "b": pa.array(np.maximum(a, b), pa.int64())})

    return run


def _pairs_of_whole(rest: DataFrame, nodes: DataFrame, percent: int) -> DataFrame:
    """(a, b) of torn groups that are small enough to be compared whole; each member is sent once."""
    sketched = rest.select("key", "node", "part", "n").join(nodes.select("node", "sketch"), "node")
    return sketched.groupBy("key").applyInArrow(_near_in_group(percent), "a long, b long").distinct()


def _met(rest: DataFrame, percent: int, block: int) -> tuple[DataFrame, DataFrame]:
    """Two sides of rest(key, node, part, n, ...) that meet on (key, size, i, j): each pair of a group of about the same size once.

    Sizes fall into ranges by powers of a little more than the largest ratio; the smaller set
    of a pair is in the range of the larger one or the one before. Members of a range with
    more than `block` are dealt over blocks by hash, and each block meets each.
    """
    ratio = float(np.log(100 / percent * 1.005))
    ranged = rest.withColumn("size", F.floor(F.log(F.col("n").cast("double")) / ratio).cast("int"))
    smaller = ranged.withColumn("size", F.explode(F.array("size", F.col("size") + 1)))
    many = smaller.groupBy("key", "size").agg(F.ceil(F.count(F.lit(1)) / block).cast("int").alias("blocks")).where("blocks > 1")
    few = F.broadcast(many) if many.limit(BROADCAST_IDS + 1).count() <= BROADCAST_IDS else many
    own = F.pmod(F.xxhash64(F.lit(3), "node"), F.coalesce("blocks", F.lit(1))).cast("int")
    each = F.explode(F.sequence(F.lit(0), F.coalesce("blocks", F.lit(1)) - 1))
    x = ranged.join(few, ["key", "size"], "left").withColumn("i", own).withColumn("j", each).drop("blocks")
    y = smaller.join(few, ["key", "size"], "left").withColumn("j", own).withColumn("i", each).drop("blocks")
    return x, y


def _pairs_of_tier(rest: DataFrame, nodes: DataFrame, tier: int, percent: int, block: int) -> DataFrame:
    """(a, b) of torn groups whose larger set belongs to the tier, by sizes and a sketch bound inside the join."""
    (top, words), low = TIERS[tier], TIERS[tier - 1][0] if tier else 0
    fits = f"n < {top} AND n * 100 >= {low} * {percent}"
    kind = ", ".join(f"q{i} long" for i in range(words)) if words <= COLUMNS else "q array<long>"
    sketches = nodes.where(fits).select("node", "sketch").mapInArrow(released(_folded(words)), f"node long, {kind}")
    x, y = _met(rest.where(fits), percent, block)
    if words <= COLUMNS:
        apart = " + ".join(f"bit_count(x.q{i} ^ y.q{i})" for i in range(words))
    else:
        apart = "aggregate(zip_with(x.q, y.q, (v, w) -> bit_count(v ^ w)), 0, (v, w) -> v + w)"
    meet = "x.key = y.key AND x.size = y.size AND x.i = y.i AND x.j = y.j AND x.part <> y.part"
    sizes = f"(x.n > y.n OR x.n = y.n AND x.node < y.node) AND y.n * 100 >= x.n * {percent} AND x.n >= {low}"
    close = F.expr(f"{meet} AND {sizes} AND ({apart}) * {100 + percent} <= (x.n + y.n) * {100 - percent}")
    met = x.join(sketches, "node").alias("x").join(y.join(sketches, "node").alias("y"), close)
    return met.select(F.least("x.node", "y.node").alias("a"), F.greatest("x.node", "y.node").alias("b")).distinct()


def _near_by_sketch(percent: int):
    def run(batches):
        for batch in batches:
            for at in range(0, batch.num_rows, 1024):
                part = batch.slice(at, 1024)
                na, nb, sa, sb = (part.column(i).to_pylist() for i in range(2, 6))
                keep = [(100 - percent) * (w + x) // (100 + percent) >= sketch_distance(y, z) for w, x, y, z in zip(na, nb, sa, sb, strict=True)]
                yield part.filter(pa.array(keep, pa.bool_())).select(["a", "b", "rep_a", "rep_b"])

    return run


def _verify(width: int, percent: int, other: dict, bits: int = 64):
    """(a, b, text_a, text_b): keeps the pairs whose whole sets are similar enough."""

    def run(batches):
        cache, sets = WordHashes(), {}

        def of(text):
            s = sets.get(text)
            if s is None:
                if len(sets) > 256 or sum(len(x[0]) for x in sets.values()) > 2_000_000:
                    sets.clear()
                s = shingle_set(text, width, cache)
                s = sets[text] = (s, known_as(set_digest(s), other, bits))
            return s

        for batch in batches:
            for at in range(0, batch.num_rows, 256):
                part = batch.slice(at, 256)
                a, b = part.column(0).to_pylist(), part.column(1).to_pylist()
                ok = []
                for x, y, s, t in zip(a, b, part.column(2).cast(pa.binary()).to_pylist(), part.column(3).cast(pa.binary()).to_pylist(), strict=True):
                    (s, s_node), (t, t_node) = of(s), of(t)
                    if (s_node, t_node) != (x, y):  # another text under a repeated id
                        ok.append(False)
                        continue
                    both = np.sort(np.r_[s, t], kind="stable")
                    common = int((both[1:] == both[:-1]).sum())
                    ok.append(100 * common >= percent * (len(s) + len(t) - common))
                yield part.filter(pa.array(ok)).select(["a", "b"])

    return run


def _dealt(pairs: DataFrame, texts: DataFrame, end: str, by: str, busy: list[DataFrame]) -> DataFrame:
    """pairs with text_<end> of the row that rep_<end> names.

    An end with many pairs is dealt over salts by the hash of column `by`; busy gets the table of these.
    """
    rep, name = f"rep_{end}", f"text_{end}"
    many = pairs.groupBy(rep).agg(F.ceil(F.count(F.lit(1)) / PARTNERS).cast("int").alias("salts")).where("salts > 1")
    many = materialize(many.withColumnRenamed(rep, "busy"), "busy")
    busy.append(many)
    few = F.broadcast(many) if many.count() <= BROADCAST_IDS else many
    salted = pairs.join(few, F.col(rep).eqNullSafe(F.col("busy")), "left")
    salted = salted.withColumn("salt", F.pmod(F.xxhash64(by), F.coalesce("salts", F.lit(1))).cast("int")).drop("busy", "salts")
    side = texts.join(few, F.col("doc_id").eqNullSafe(F.col("busy")), "left")
    side = side.select(F.col("doc_id").alias("own"), F.col("text").alias(name), F.explode(F.sequence(F.lit(0), F.coalesce("salts", F.lit(1)) - 1)).alias("at"))
    return salted.join(side, salted[rep].eqNullSafe(F.col("own")) & (F.col("salt") == F.col("at"))).drop("own", "at", "salt", rep)


def _verified(
    pairs: DataFrame, nodes: DataFrame, docs: DataFrame, width: int, percent: int, other: dict, bits: int = 64, compared: bool = False
) -> DataFrame:
    """Of the candidate pairs (a, b), those that are links. compared: their sketches are known to be near and stay where they are."""
    own = ("rep",) if compared else ("rep", "n", "sketch")
    end = lambda x: nodes.select(*(F.col(c).alias(f"{c}_{x}") for c in own), F.col("node").alias(x))
    near = pairs.join(end("a"), "a").join(end("b"), "b").select("a", "b", *(f"{c}_{x}" for c in (*own[1:], "rep") for x in "ab"))
    if not compared:
        near = near.mapInArrow(released(_near_by_sketch(percent)), "a long, b long, rep_a long, rep_b long")
    near = materialize(near, "near")
    wanted = materialize(near.select(F.explode(F.array("rep_a", "rep_b")).alias("rep")).distinct(), "wanted")
    ids = F.broadcast(wanted) if wanted.count() <= BROADCAST_IDS else wanted
    texts = docs.join(ids, docs.doc_id.eqNullSafe(ids.rep), "left_semi")
    busy: list[DataFrame] = []
    both = _dealt(_dealt(near, texts, "b", "a", busy), texts, "a", "b", busy)
    found = both.select("a", "b", "text_a", "text_b").mapInArrow(released(_verify(width, percent, other, bits)), "a long, b long")
    links = materialize(found.distinct(), "links")
    discard(near, wanted, *busy)
    return links


def _components(links: DataFrame) -> DataFrame:
    if links.count() <= LOCAL_LINKS:
        return materialize(local_components(links, LOCAL_LINKS), "parts")
    return materialize(star_components(links), "parts")


def _torn(member: DataFrame, parts: DataFrame) -> DataFrame:
    """(key, node, n, part, c) of the groups with members in several components, c members each; of groups with the same members one: count and two sums tell them."""
    part = F.coalesce("component", "node").alias("part")
    placed = materialize(member.join(parts.withColumnRenamed("id", "node"), "node", "left").select("key", "node", "n", part), "placed")
    sums = (F.sum(F.shiftright(F.xxhash64(F.lit(i), "node"), 24)).alias(f"h{i}") for i in (0, 1))
    per = placed.groupBy("key").agg(F.min("part").alias("p0"), F.max("part").alias("p1"), F.count(F.lit(1)).alias("c"), *sums)
    torn = per.where("p0 <> p1").groupBy("c", "h0", "h1").agg(F.min("key").alias("key")).select("key", "c")
    rest = materialize(placed.join(torn, "key"), "torn")
    discard(placed)
    return rest


def _first_ties(ties: DataFrame) -> DataFrame:
    """Pairs (a, b), a < b, of ties(own, other): at most TIES of each own."""
    w = Window.partitionBy("own").orderBy(F.xxhash64("other"))
    some = ties.withColumn("r", F.row_number().over(w)).where(F.col("r") <= TIES)
    return some.select(F.least("own", "other").alias("a"), F.greatest("own", "other").alias("b")).distinct()


def _renamed(rows: DataFrame) -> tuple[DataFrame, dict]:
    """rows with numbers of their own for different sets that share a first digest, and these numbers by both digests.

    Among n sets about n * n / 2**65 share one, so the list is short at any size that fits a disk.
    """
    clash = rows.where("n > 0").groupBy("node").agg(F.min("check").alias("c0"), F.max("check").alias("c1")).where("c0 <> c1").select("node", "c0")
    if not clash.limit(1).count():
        return rows, {}
    found = rows.where("n > 0").join(clash, "node").where("check <> c0").select("node", "check").distinct()
    other = {(r.node, r.check): r.own for r in found.select("node", "check", F.xxhash64(F.lit(11), "node", "check").alias("own")).collect()}
    table = F.broadcast(rows.sparkSession.createDataFrame([(*k, v) for k, v in other.items()], "node long, check long, own long"))
    return rows.join(table, ["node", "check"], "left").withColumn("node", F.coalesce("own", "node")).drop("own"), other


def jaccard_components(
    docs: DataFrame, width: int = 5, percent: int = 75, frequent_from: int = 6, hot_from: int = HOT, block: int = BLOCK, digest_bits: int = 64,
    with_keys: bool = False,
) -> DataFrame:
    """(doc_id, n_shingles, component_id) for every row of docs(doc_id BIGINT, text).

    Texts link when 100 * |A & B| >= percent * |A | B| over their sets of `width`-word
    shingles; component_id is the smallest doc_id that links reach, itself included. Empty
    and null texts have no shingles and are linked with nothing. Repeated rows each get a
    row; equal texts share a component. A row without doc_id gets the component of its links,
    and null if they have no doc_id either. Other columns are ignored. Every link between
    different texts is found: nothing is capped or sampled. with_keys adds h1 and h2, two
    hashes of the text, and part, which names the component also where a doc_id stands on
    rows of several; it is null without shingles. digest_bits is for tests.
    """
    spark = docs.sparkSession
    docs = docs.select(F.col("doc_id").cast("long").alias("doc_id"), F.col("text").cast("string").alias("text"))
    kind = "kind int, doc_id long, h1 long, h2 long, n long, node long, check long, sketch binary"
    h1, h2 = text_key(F.col("text"))
    keyed = docs.select("doc_id", h1.alias("h1"), h2.alias("h2"), "text")
    all_rows = materialize(keyed.mapInArrow(released(_describe(width, percent, digest_bits)), kind), "described")
    rows, other = _renamed(all_rows.where("kind = 0"))
    node = rows.where("n > 0").groupBy("node").agg(F.min("doc_id").alias("rep"), F.min("n").alias("n"), F.first("sketch").alias("sketch"))
    nodes = materialize(node, "nodes")
    total = nodes.agg(F.sum("n").alias("n")).first().n or 0
    counted = all_rows.where("kind = 1").groupBy(F.col("node").alias("key")).agg(F.sum("n").alias("c"))
    top = counted.where(F.col("c") >= frequent_from).orderBy(F.desc("c"), "key").limit(FREQUENT).collect()
    value, count = np.array([r.key for r in top], np.int64).view(np.uint64), np.array([r.c for r in top], np.int64)
    order = np.argsort(value)
    ranked = spark.sparkContext.broadcast((value[order], count[order]))
    very = order[count[order] >= hot_from]
    hot = spark.sparkContext.broadcast((value[very], -(-count[very] // hot_from)))

    least = int(spark.conf.get("spark.sql.shuffle.partitions"))
    buckets = max(least, int(total * 0.4 // 1_500_000) + 1)
    emitted = released(_emit(width, percent, buckets, ranked, hot, other, digest_bits))
    packed = docs.select("text").mapInArrow(emitted, "bucket int, keys binary, nodes binary, sizes binary")
    grouped = packed.repartition(buckets, "bucket").mapInArrow(released(_group(percent, hot)), "kind int, key long, a long, b long, n long")
    groups = materialize(grouped, "groups")

    verified = lambda pairs: _verified(pairs, nodes, docs, width, percent, other, digest_bits)
    pairs = groups.where("kind = 0").select("a", "b")
    large = groups.where("kind = 1").limit(1).count() > 0
    if large:
        member = materialize(_merged(groups.where("kind = 1").select("key", F.col("a").alias("node"), "n").distinct()), "member")
        ties = member.where("node <> pivot").select(F.col("node").alias("own"), F.col("pivot").alias("other")).distinct()
        pairs = pairs.unionAll(_first_ties(ties))
    pairs = materialize(pairs.distinct(), "pairs")
    parts = _components(verified(pairs))
    discard(groups, pairs)
    if large:
        join_parts = lambda more: _components(parts.select(F.col("id").alias("a"), F.col("component").alias("b")).unionAll(more))
        rest = _torn(member, parts)
        torn = materialize(rest.select("node").distinct(), "torn-ids")
        ids = F.broadcast(torn) if torn.count() <= BROADCAST_IDS else torn
        torn_nodes = materialize(nodes.join(ids, "node", "left_semi"), "torn-nodes")
        checked = lambda pairs, **how: _verified(pairs, torn_nodes, docs, width, percent, other, digest_bits, **how)
        whole = materialize(_pairs_of_whole(rest.where(F.col("c") <= MEET), torn_nodes, percent), "whole")
        first, rest = rest, materialize(rest.where(F.col("c") > MEET), "large")
        discard(first, member, torn)
        if rest.limit(1).count():
            words = TIERS[0][1]
            of_large = torn_nodes.join(rest.select("node").distinct(), "node", "left_semi").select("node", "sketch")
            coarse = of_large.mapInArrow(released(_folded(words)), "node long, " + ", ".join(f"q{i} long" for i in range(words)))
            coarse = materialize(coarse.select("node", F.struct(*(f"q{i}" for i in range(words))).alias("q")), "coarse")
            for turn in range(TURNS):
                ties = _pivot_ties(rest, coarse, percent, turn)
                more = checked(ties) if ties.limit(1).count() else None
                discard(ties)
                if more is None or not more.limit(1).count():
                    break
                parts = join_parts(more)
                before, rest = rest, _torn(rest.select("key", "node", "n"), parts)
                discard(before)
            discard(coarse)
        of_tier = lambda i: F.count_if(F.expr(f"n < {TIERS[i][0]} AND n * 100 >= {TIERS[i - 1][0] if i else 0} * {percent}"))
        found = rest.agg(*(of_tier(i).alias(f"t{i}") for i in range(len(TIERS)))).first()
        cross = [_pairs_of_tier(rest, torn_nodes, i, percent, block) for i in range(len(TIERS)) if found[i]]
        cross = materialize(reduce(DataFrame.unionAll, cross, whole).distinct(), "cross")
        if cross.limit(1).count():
            parts = join_parts(checked(cross, compared=True))
        discard(cross, whole, torn_nodes)
        discard(rest)
    mark = nodes.select("node", "rep").join(parts.withColumnRenamed("id", "node"), "node", "left")
    mark = mark.select("node", "rep", F.coalesce("component", "node").alias("part"))
    least_id = mark.groupBy("part").agg(F.min("rep").alias("component_id"))
    named = mark.join(least_id, "part").select("node", "component_id", "part")
    full, bare = rows.where("n > 0").join(named, "node"), rows.where("n = 0").withColumns({"component_id": F.col("doc_id"), "part": F.lit(None).cast("long")})
    shown = ["doc_id", F.col("n").alias("n_shingles"), "component_id", *(["h1", "h2", "part"] if with_keys else [])]
    return full.select(*shown).unionAll(bare.select(*shown))
