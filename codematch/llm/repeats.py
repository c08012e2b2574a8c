"""Repeated byte strings of a whole corpus, through local enhanced suffix arrays.

Any string of SPAN bytes holds a place whose hash of GRAM bytes is the least among its
SPAN - GRAM + 1 (the first such on a tie), and equal strings have it at the same place. So
equal strings are found by the hash at their place: places whose hash occurs once in the
corpus go; the others send their context, the union of the strings they stand for, to the
partition of their hash. There

1. rolling hashes of the strings find those that occur twice;
2. of these, only strings that cannot be extended to the left in the same way everywhere
   (the byte before differs, or a context begins) stay as suffixes: left-extension diversity;
3. the suffixes are sorted, and a stack scan over their common-prefix lengths yields the
   interval tree: every interval of at least SPAN bytes is a maximal repeat group, with all
   its occurrences and not just neighbours.

What the groups cover is cut from the texts. Equal texts are handled once. Equal contexts
are are sent once by each task. Places of a frequent hash are dealt over as many partitions as
their number asks for; strings that are single in theirs then meet by two hashes.

Texts are known by a 64-bit hash. Where different texts share one, which a second hash shows,
all but one of them get another number, so identity is by 128 bits.
"""

from __future__ import annotations

import hashlib
from collections.abc import Iterator
from itertools import islice

import numpy as np
import pyarrow as pa
import xxhash
from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

from codematch.functions.arrays import text_key
from codematch.llm.shingles import mix
from codematch.llm.workers import released
from codematch.sources.io import discard, materialize

SPAN, GRAM = 200, 32
#: Bytes handled at once; longer texts go in pieces that overlap by what a string needs.
PIECE = 1 << 18
#: Places of a hash that go to one partition; those of a more frequent one are dealt over several.
HOT = 10_000
#: Places in a bucket, and places that a task packs at once.
BUCKET, PACKED = 500_000, 100_000
BROADCAST_IDS = 500_000
_BASE = 0x9E3779B97F4A7C55
_POWERS: list[np.ndarray] = []
#: Seed that Spark's xxhash64 has after the integer 7, as in text_key.
_SECOND = xxhash.xxh64_intdigest((7).to_bytes(4, "little"), seed=42)


def powers(n: int) -> tuple[np.ndarray, np.ndarray]:
    """_BASE**i and its inverse**i modulo 2**64, for i <= n at least."""
    if not _POWERS or len(_POWERS[0]) <= n:
        size = 1 << max(12, int(n).bit_length())
        inverse = pow(_BASE, -1, 1 << 64)
        _POWERS[:] = [np.cumprod(np.r_[np.uint64(1), np.full(size, np.uint64(b))], dtype=np.uint64) for b in (_BASE, inverse)]
    return _POWERS[0], _POWERS[1]


def prefix_sums(data: np.ndarray, table: int = 0) -> np.ndarray:
    up, _ = powers(len(data))
    return np.r_[np.uint64(0), np.cumsum(mix_bytes(table)[data] * up[: len(data)], dtype=np.uint64)]


_TABLES: list[np.ndarray] = []


def mix_bytes(table: int = 0) -> np.ndarray:
    """A random-looking odd 64-bit word for each byte; two tables."""
    if not _TABLES:
        _TABLES.extend(mix(np.arange(1, 257, dtype=np.uint64), salt) | np.uint64(1) for salt in (0x5151, 0xA3A3A3))
    return _TABLES[table]


def rolling(sums: np.ndarray, width: int) -> np.ndarray:
    """A hash of each run of `width` bytes, from prefix_sums."""
    n = len(sums) - width
    _, down = powers(len(sums))
    return mix((sums[width:] - sums[:n]) * down[:n]) if n > 0 else np.empty(0, np.uint64)


def sliding_min(x: np.ndarray, width: int) -> np.ndarray:
    """The least of each `width` consecutive values, in linear time: prefix and suffix minima of blocks."""
    n = len(x) - width + 1
    blocks = -(-len(x) // width)
    full = np.full(blocks * width, np.iinfo(x.dtype).max, x.dtype)
    full[: len(x)] = x
    grid = full.reshape(blocks, width)
    ahead = np.minimum.accumulate(grid, axis=1).ravel()
    back = np.minimum.accumulate(grid[:, ::-1], axis=1)[:, ::-1].ravel()
    return np.minimum(back[:n], ahead[width - 1 : width - 1 + n])


def anchors(data: np.ndarray, span: int, gram: int) -> tuple[np.ndarray, np.ndarray, np.ndarray, np.ndarray]:
    """(place, hash, first string start, last string start) of each chosen place of a text."""
    out = []
    step = PIECE
    for at in range(0, max(len(data) - span + 1, 0), step):
        part = data[at : at + step + span - 1]
        h = rolling(prefix_sums(part), gram)
        low = np.uint64((1 << 23) - 1)  # places of a piece fit: PIECE + span < 2**23
        packed = (h & ~low) | np.arange(len(h), dtype=np.uint64)
        best = (sliding_min(packed, span - gram + 1) & low).astype(np.int64)
        new = np.flatnonzero(np.r_[True, best[1:] != best[:-1]])
        end = np.r_[new[1:], len(best)] - 1
        place = best[new]
        out.append((place + at, h[place], new + at, end + at))
    if not out:
        return (np.empty(0, np.int64), np.empty(0, np.uint64), np.empty(0, np.int64), np.empty(0, np.int64))
    return tuple(np.concatenate(c) for c in zip(*out, strict=True))


def suffix_order(data: bytes, starts: np.ndarray, ends: np.ndarray) -> np.ndarray:
    """Sparse suffix array: the order of the suffixes [start, end) of data, equal ones by start."""
    view = [data[i:j] for i, j in zip(starts.tolist(), ends.tolist(), strict=True)]
    return np.array(sorted(range(len(view)), key=view.__getitem__), np.int64)


def common_prefixes(data: np.ndarray, starts: np.ndarray, ends: np.ndarray, limit: int = 4096) -> np.ndarray:
    """Length of the common prefix of each suffix with the one before it; 0 for the first."""
    n = len(starts)
    out = np.zeros(n, np.int64)
    if n < 2:
        return out
    room = np.minimum(ends[1:] - starts[1:], ends[:-1] - starts[:-1])
    live, done = np.arange(n - 1), np.zeros(n - 1, np.int64)
    width = 64
    while len(live):
        for at in range(0, len(live), 1 << 15):
            i = live[at : at + (1 << 15)]
            reach = np.arange(width)
            here = done[i][:, None] + reach
            inside = here < room[i][:, None]
            x = data[np.minimum(starts[:-1][i][:, None] + here, len(data) - 1)]
            y = data[np.minimum(starts[1:][i][:, None] + here, len(data) - 1)]
            same = (x == y) & inside
            run = np.where(same.all(1), width, same.argmin(1))
            done[i] += run
        live = live[(done[live] < room[live]) & (done[live] % width == 0) & (done[live] > 0) & (data[np.minimum(starts[:-1][live] + done[live], len(data) - 1)] == data[np.minimum(starts[1:][live] + done[live], len(data) - 1)])]
    out[1:] = done
    return out


def intervals(lcp: np.ndarray, least: int) -> list[tuple[int, int, int, int]]:
    """Nodes of the common-prefix interval tree of at least `least`: (length, first, last, parent index or -1).

    One stack scan; children come before their parents.
    """
    out: list[list[int]] = []
    stack: list[list] = []  # length, first, children
    for i in range(1, len(lcp) + 1):
        now = int(lcp[i]) if i < len(lcp) else 0
        first, kids = i - 1, []
        while stack and stack[-1][0] > now:
            length, first, own = stack.pop()
            own = own + kids
            out.append([length, first, i - 1, -1])
            for k in own:
                out[k][3] = len(out) - 1
            kids = [len(out) - 1]
        if now >= least:
            if stack and stack[-1][0] == now:
                stack[-1][2].extend(kids)
            else:
                stack.append([now, first, kids])
    return [tuple(x) for x in out]


def maximal_repeats(contexts: list[bytes], span: int) -> tuple[list[tuple[int, np.ndarray, np.ndarray]], np.ndarray, np.ndarray]:
    """Maximal repeat groups of a list of contexts, as (length, context numbers, offsets in them).

    Also the context numbers and offsets of the strings of `span` bytes whose hash no other has.
    """
    lengths = np.fromiter(map(len, contexts), np.int64, len(contexts))
    data = b"".join(contexts)
    flat = np.frombuffer(data, np.uint8)
    base = np.r_[0, np.cumsum(lengths)]
    counts = np.maximum(lengths - span + 1, 0)
    which = np.repeat(np.arange(len(contexts), dtype=np.int32), counts)
    offset = (np.arange(len(which)) - np.repeat(np.r_[0, np.cumsum(counts)][:-1], counts)).astype(np.int32)
    start = base[which] + offset
    h = rolling(prefix_sums(flat), span)[start] if len(start) else np.empty(0, np.uint64)
    order = np.argsort(h, kind="stable")
    ranked = h[order]
    edge = np.flatnonzero(np.r_[True, ranked[1:] != ranked[:-1]]) if len(h) else np.empty(0, np.int64)
    many = np.diff(np.r_[edge, len(h)])
    del h, ranked
    single = order[edge[many == 1]]
    alone = which[single], offset[single]
    if not (many > 1).any():
        return [], *alone
    before = np.where(offset[order] > 0, flat[np.maximum(start[order] - 1, 0)].astype(np.int16), np.int16(-1))
    low, high = np.minimum.reduceat(before, edge), np.maximum.reduceat(before, edge)
    keep = np.repeat((many > 1) & ((low != high) | (low < 0)), many)
    chosen = order[keep]
    del order, before, keep
    s, e = start[chosen], base[which[chosen] + 1]
    rank = suffix_order(data, s, e)
    s, e, chosen = s[rank], e[rank], chosen[rank]
    lcp = common_prefixes(flat, s, e)
    groups = [(length, which[chosen[i : j + 1]], offset[chosen[i : j + 1]]) for length, i, j, _ in intervals(lcp, span)]
    return groups, *alone


def two_hashes(contexts: list[bytes], which: np.ndarray, offset: np.ndarray, span: int) -> list[list[int]]:
    """Both hashes, as signed integers, of the strings of `span` bytes at these offsets of these contexts."""
    flat = np.frombuffer(b"".join(contexts), np.uint8)
    at = np.r_[0, np.cumsum(np.fromiter(map(len, contexts), np.int64, len(contexts)))][which] + offset
    return [rolling(prefix_sums(flat, table), span)[at].view(np.int64).tolist() for table in (0, 1)] if len(at) else [[], []]


def covered_runs(spans: list[tuple[int, int]]) -> list[tuple[int, int]]:
    """Sorted, merged runs; touching ones are one."""
    out: list[list[int]] = []
    for s, e in sorted(spans):
        if out and s <= out[-1][1]:
            out[-1][1] = max(out[-1][1], e)
        else:
            out.append([s, e])
    return [tuple(x) for x in out]


# ---- the passes over the corpus

_PACKED = pa.schema([("bucket", pa.int32()), ("hashes", pa.binary()), ("nodes", pa.binary()), ("places", pa.binary()), ("firsts", pa.binary()), ("lasts", pa.binary())])
_MARKED = pa.schema([("node", pa.int64()), ("hash", pa.int64()), ("first", pa.int32()), ("last", pa.int32()), ("salts", pa.int32())])
_SENT = pa.schema([("hash", pa.int64()), ("node", pa.int64()), ("first", pa.int32()), ("salts", pa.int32()), ("context", pa.binary()), ("end", pa.int32())])
_SPANS = pa.schema([("node", pa.int64()), ("start", pa.int32()), ("end", pa.int32()), ("single", pa.int64()), ("second", pa.int64()), ("seen", pa.int32())])
_DTYPES = (np.uint64, np.int64, np.int32, np.int32, np.int32)


def _signed(x: int) -> int:
    return x - (x >> 63 << 64)


def node_of(text: bytes, other: dict, bits: int = 64) -> int:
    """The number of a text: Spark's xxhash64, or what `other` has for it and a second hash (see _numbered)."""
    first = xxhash.xxh64_intdigest(text, seed=42)
    if not other and bits >= 64:
        return _signed(first)
    cut = _signed(first) if bits >= 64 else first & ((1 << bits) - 1)
    return other.get((cut, _signed(xxhash.xxh64_intdigest(text, seed=_SECOND))), cut)


def _numbered(first: Column, second: Column, other: dict) -> Column:
    """The same number from a text's two hashes, in the JVM."""
    out = first
    for (a, b), own in other.items():
        out = F.when((first == a) & (second == b), F.lit(own)).otherwise(out)
    return out


def _texts(batch: pa.RecordBatch, column: int, size: int = 256) -> Iterator[tuple[int, bytes]]:
    for at in range(0, batch.num_rows, size):
        part = batch.column(column).slice(at, size).cast(pa.binary()).to_pylist()
        yield from ((at + i, x or b"") for i, x in enumerate(part))


def _find_anchors(span: int, gram: int, buckets: int, other: dict, bits: int = 64):
    def run(batches):
        rows, kept, seen = [], 0, set()

        def pack():
            h, v, p, a, b = (np.concatenate([r[i] for r in rows]) for i in range(5))
            to = ((h >> np.uint64(20)) % np.uint64(buckets)).astype(np.int64)
            order = np.argsort(to, kind="stable")
            to = to[order]
            at = np.flatnonzero(np.r_[True, to[1:] != to[:-1]])
            ends = np.r_[at[1:], len(to)]
            cols = [pa.array([x[i:j].tobytes() for i, j in zip(at, ends, strict=True)], pa.binary()) for x in (y[order].astype(t) for y, t in zip((h, v, p, a, b), _DTYPES, strict=True))]
            return pa.RecordBatch.from_arrays([pa.array(to[at].astype(np.int32)), *cols], schema=_PACKED)

        for batch in batches:
            for _, text in _texts(batch, 0):
                if len(text) < span:
                    continue
                node = node_of(text, other, bits)
                if node in seen:
                    continue
                seen.add(node)
                place, h, first, last = anchors(np.frombuffer(text, np.uint8), span, gram)
                rows.append((h, np.full(len(h), node, np.int64), place, first, last))
                kept += len(h)
                if kept > PACKED:
                    yield pack()
                    rows, kept = [], 0
            if len(seen) > 200_000:
                seen.clear()
        if kept:
            yield pack()

    return run


def _mark_repeated(hot_from: int):
    """Of the places of a bucket, those whose hash has several, as rows of their texts; salts: partitions that they ask for."""

    def run(batches):
        by: dict[int, list] = {}
        for batch in batches:
            for to, *cols in zip(*(batch.column(i).to_pylist() for i in range(6)), strict=True):
                by.setdefault(to, []).append([np.frombuffer(x, t) for x, t in zip(cols, _DTYPES, strict=True)])
        for to in list(by):
            h, v, p, a, b = (np.concatenate(x) for x in zip(*by.pop(to), strict=True))
            order = np.lexsort((a, p, v, h))
            h, v, p, a, b = h[order], v[order], p[order], a[order], b[order]
            new = np.r_[True, (h[1:] != h[:-1]) | (v[1:] != v[:-1]) | (p[1:] != p[:-1]) | (a[1:] != a[:-1])]
            h, v, a, b = h[new], v[new], a[new], b[new]
            at = np.flatnonzero(np.r_[True, h[1:] != h[:-1]])
            many = np.diff(np.r_[at, len(h)])
            keep, salts = np.flatnonzero(np.repeat(many > 1, many)), np.repeat(-(-many // hot_from), many).astype(np.int32)
            for i in range(0, len(keep), 200_000):
                j = keep[i : i + 200_000]
                yield pa.RecordBatch.from_pydict({"node": v[j], "hash": h[j].view(np.int64), "first": a[j], "last": b[j], "salts": salts[j]}, _MARKED)

    return run


def _send_contexts(span: int, other: dict, bits: int = 64):
    """(text, marks) -> contexts, equal ones once for each task; a context met before sends no bytes but covers itself."""

    def run(batches):
        seen: dict[bytes, list] = {}
        size = 0
        for batch in batches:
            for at in range(0, batch.num_rows, 128):
                part = batch.slice(at, 128)
                rows: list[tuple] = []
                for text, marks in zip(part.column(0).cast(pa.binary()).to_pylist(), part.column(1).to_pylist(), strict=True):
                    node = node_of(text, other, bits)
                    for m in marks:
                        context = text[m["first"] : m["last"] + span]
                        key = xxhash.xxh3_128_digest(context)
                        old = seen.get(key)
                        if old is None:
                            seen[key] = [node, m["first"]]
                            size += 1
                            rows.append((m["hash"], node, m["first"], m["salts"], context, m["last"] + span))
                            continue
                        if old:  # the first of its kind is repeated as well
                            rows.append((None, old[0], old[1], 1, None, old[1] + len(context)))
                            seen[key] = []
                        rows.append((None, node, m["first"], 1, None, m["last"] + span))
                if rows:
                    yield pa.RecordBatch.from_arrays([pa.array(c, f.type) for c, f in zip(zip(*rows, strict=True), _SENT, strict=True)], schema=_SENT)
                if size > 200_000:
                    seen, size = {}, 0

    return run


def _cover(span: int):
    """Contexts of a partition -> spans of repeat groups; strings of frequent places that are single here go on by hash."""

    def spans_of(rows: list[tuple], hot: bool):
        contexts = [r[2] for r in rows]
        groups, single, at = maximal_repeats(contexts, span)
        out: dict[int, list] = {}
        for length, which, offset in groups:
            for w, o in zip(which.tolist(), offset.tolist(), strict=True):
                out.setdefault(w, []).append((o, o + length))
        for w, x in out.items():
            for s, e in covered_runs(x):
                yield rows[w][0], rows[w][1] + s, rows[w][1] + e, None, None, None
        if hot:
            for w, o, h, k in zip(single.tolist(), at.tolist(), *two_hashes(contexts, single, at, span), strict=True):
                yield rows[w][0], rows[w][1] + o, rows[w][1] + o + span, h, k, 1
            known = {}
            for length, which, offset in groups:  # one of each string that is repeated here stands for it elsewhere
                w, o = int(which[0]), int(offset[0])
                for x in range(o, o + length - span + 1):
                    known.setdefault(contexts[w][x : x + span], None)
            strings = list(known)
            for h, k in zip(*two_hashes(strings, np.arange(len(strings)), np.zeros(len(strings), np.int64), span), strict=True):
                yield None, None, None, h, k, 2

    def flush(rows: list[tuple]):
        for hot in (False, True):
            part = [r[:3] for r in rows if (r[3] > 1) == hot]
            spans = spans_of(part, hot) if part else iter(())
            while some := list(islice(spans, 50_000)):
                yield pa.RecordBatch.from_arrays([pa.array(c, f.type) for c, f in zip(zip(*some, strict=True), _SPANS, strict=True)], schema=_SPANS)

    def run(batches):
        rows: list[tuple] = []
        size, last = 0, None
        for batch in batches:  # sorted by hash: a chunk ends only between two hashes
            for h, node, first, salts, context in zip(*(batch.column(i).to_pylist() for i in range(5)), strict=True):
                if size > 1_000_000 and h != last:
                    yield from flush(rows)
                    rows, size = [], 0
                rows.append((node, first, context, salts))
                size += len(context)
                last = h
        yield from flush(rows)

    return run


def _cut(other: dict, bits: int = 64):
    """(text, spans) -> node, n_removed, n_spans, kept_sha256, kept."""
    schema = pa.schema([("node", pa.int64()), ("n_removed", pa.int64()), ("n_spans", pa.int64()), ("kept_sha256", pa.string()), ("kept", pa.string())])

    def run(batches):
        for batch in batches:
            for at in range(0, batch.num_rows, 128):
                part = batch.slice(at, 128)
                out = []
                for text, spans in zip(part.column(0).cast(pa.binary()).to_pylist(), part.column(1).to_pylist(), strict=True):
                    runs = covered_runs([(s["start"], s["end"]) for s in spans])
                    kept, end = [], 0
                    for s, e in runs:
                        kept.append(text[end:s])
                        end = e
                    kept = b"".join([*kept, text[end:]])
                    out.append((node_of(text, other, bits), len(text) - len(kept), len(runs), hashlib.sha256(kept).hexdigest(), kept.decode("utf-8", "ignore")))
                if out:
                    yield pa.RecordBatch.from_arrays([pa.array(c, f.type) for c, f in zip(zip(*out, strict=True), schema, strict=True)], schema=schema)

    return run


class Texts:
    """The distinct texts of docs(doc_id, text), by number.

    reps: (node, rep, copies, n_bytes), a row for each; node: its column over docs.text; other:
    numbers by both hashes, of texts whose first hash another one has. Among n texts about
    n * n / 2**65 share one, so that list is short at any size that fits a disk.
    """

    def __init__(self, docs: DataFrame, bits: int = 64):
        h1, h2 = text_key(F.col("text"))
        first = h1 if bits >= 64 else h1.bitwiseAND(F.lit((1 << bits) - 1))
        self.bits = bits
        light = docs.select("doc_id", F.octet_length(F.coalesce("text", F.lit(""))).alias("n_bytes"), first.alias("first"), h2.alias("second"))
        per = light.groupBy("first", "second").agg(F.min("doc_id").alias("rep"), F.count(F.lit(1)).alias("copies"), F.max("n_bytes").alias("n_bytes"))
        per = materialize(per, "texts")
        least = per.groupBy("first").agg(F.min("second").alias("kept"), F.max("second").alias("last")).where("kept <> last")
        found = per.join(least, "first").where("second <> kept").select("first", "second", F.xxhash64(F.lit(13), "first", "second").alias("own")).collect()
        self.other = {(r.first, r.second): r.own for r in found}
        self.node = _numbered(first, h2, self.other)
        self.reps = per.select(_numbered(F.col("first"), F.col("second"), self.other).alias("node"), "rep", "copies", "n_bytes")
        self.n_bytes = per.agg(F.sum("n_bytes").alias("n")).first().n or 0


def repeated_spans(docs: DataFrame, texts: Texts, span: int = SPAN, gram: int = GRAM, hot_from: int = HOT) -> DataFrame:
    """The repeated spans (node, start, end) of distinct texts, those left out that are short."""
    spark = docs.sparkSession
    other, bits = texts.other, texts.bits
    least = int(spark.conf.get("spark.sql.shuffle.partitions"))
    buckets = max(least, int(texts.n_bytes / 85 / BUCKET) + 1)
    long = docs.where(F.octet_length("text") >= span)
    found = long.select("text").mapInArrow(released(_find_anchors(span, gram, buckets, other, bits)), "bucket int, hashes binary, nodes binary, places binary, firsts binary, lasts binary")
    marks = found.repartition(buckets, "bucket").mapInArrow(released(_mark_repeated(hot_from)), "node long, hash long, first int, last int, salts int")
    marks = materialize(marks, "marks")
    by_node = marks.groupBy("node").agg(F.collect_list(F.struct("hash", "first", "last", "salts")).alias("marks"))
    wanted = by_node.join(texts.reps.select("node", "rep"), "node").select("rep", F.col("node").alias("own"), "marks")
    full = long.select("doc_id", "text", texts.node.alias("node"))
    sent = full.join(wanted, full.doc_id.eqNullSafe(wanted.rep) & (F.col("node") == F.col("own"))).select("text", "marks")
    sent = materialize(sent.mapInArrow(released(_send_contexts(span, other, bits)), "hash long, node long, first int, salts int, context binary, end int"), "contexts")
    discard(marks)
    salt = F.pmod(F.xxhash64(F.lit(5), "node", "first"), F.col("salts"))
    dealt = sent.where("context IS NOT NULL").withColumn("salt", salt).repartition(buckets, "hash", "salt").sortWithinPartitions("hash").select("hash", "node", "first", "salts", "context")
    local = dealt.mapInArrow(released(_cover(span)), "node long, start int, end int, single long, second long, seen int")
    local = materialize(local, "spans")
    met = local.where("single IS NOT NULL")
    twice = met.groupBy("single", "second").agg(F.sum("seen").alias("seen")).where("seen > 1").select("single", "second")
    late = met.where("node IS NOT NULL").join(twice, ["single", "second"], "left_semi").select("node", "start", "end")
    again = sent.where("context IS NULL").select("node", F.col("first").alias("start"), "end")
    spans = local.where("single IS NULL").select("node", "start", "end").unionAll(again).unionAll(late)
    spans._behind = (sent, local)
    return spans


def cut_repeats(
    docs: DataFrame, span: int = SPAN, gram: int = GRAM, hot_from: int = HOT, with_text: bool = False, carry: tuple[str, ...] = (), hash_bits: int = 64
) -> DataFrame:
    """One row per row of docs(doc_id BIGINT, text): doc_id, n_bytes, n_removed, n_spans, kept_sha256.

    Removes each byte that a string of `span` bytes covers which also starts anywhere else in
    the corpus, the same text included; strings are judged on the input, and never cross
    texts. Null texts count as empty; a text under `span` bytes keeps all. Repeated rows are
    copies of each other, so texts of `span` bytes or more are removed from all of them.
    with_text adds kept, the remaining text; of a character that a cut splits nothing stays.
    carry names columns of docs to return as well; others are ignored. hash_bits is for tests.
    """
    carried = F.struct(*(F.col(c).alias(f"c{i}") for i, c in enumerate(carry)), F.lit(0).alias("none")).alias("carried")
    docs = docs.select(F.col("doc_id").cast("long").alias("doc_id"), F.col("text").cast("string").alias("text"), carried)
    known = Texts(docs, hash_bits)
    plain = docs.select("doc_id", "text")
    spans = repeated_spans(plain, known, span, gram, hot_from)
    text = F.coalesce("text", F.lit(""))
    copied = (F.col("copies") > 1) & (F.col("n_bytes") >= span)
    runs = spans.groupBy("node").agg(F.collect_set(F.struct("start", "end")).alias("spans"))
    per = materialize(runs.join(known.reps.where(~copied).select("node", "rep"), "node").select(F.col("node").alias("own"), "rep", "spans"), "per_text")
    discard(*spans._behind)
    texts = plain.select("doc_id", text.alias("text"), known.node.alias("node"))
    ids = per.select("rep").distinct()
    small = F.broadcast(ids) if ids.count() <= BROADCAST_IDS else ids
    touched = texts.join(small, texts.doc_id.eqNullSafe(small.rep), "left_semi").join(per, F.col("node") == F.col("own")).select("text", "spans")
    cut = touched.mapInArrow(released(_cut(known.other, hash_bits)), "node long, n_removed long, n_spans long, kept_sha256 string, kept string").dropDuplicates(["node"])
    cut = cut if with_text else cut.drop("kept")
    whole = known.reps.where(copied).select("node", F.col("n_bytes").cast("long").alias("n_removed"), F.lit(1).cast("long").alias("n_spans"), F.sha2(F.lit(""), 256).alias("kept_sha256"), *([F.lit("").alias("kept")] if with_text else []))
    rows = docs.select("doc_id", F.octet_length(text).cast("long").alias("n_bytes"), known.node.alias("node"), F.sha2(text, 256).alias("whole"), "carried", *([text.alias("whole_text")] if with_text else []))
    out = rows.join(whole.unionAll(cut), "node", "left")
    zero = F.lit(0).cast("long")
    columns = [F.coalesce("n_removed", zero).alias("n_removed"), F.coalesce("n_spans", zero).alias("n_spans"), F.coalesce("kept_sha256", "whole").alias("kept_sha256")]
    more = [F.coalesce("kept", "whole_text").alias("kept")] if with_text else []
    return out.select("doc_id", "n_bytes", *columns, *more, *(F.col(f"carried.c{i}").alias(c) for i, c in enumerate(carry)))
