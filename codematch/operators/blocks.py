"""All pairs of compact codes, block against block.

Where tokens are frequent or bands are short, nearly all pairs meet, and a join would write
each meeting as a row. Here rows of a few numbers are dealt over blocks by hash, each pair of
blocks is one group, and pairs are compared in memory; only what is asked for comes out:
counts, maxima, or the pairs that are near. Every pair is compared, none is left out.
"""

from __future__ import annotations

from collections.abc import Callable, Iterator
from math import comb

import numpy as np
import pyarrow as pa
from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

from codematch.sources.io import materialize

#: Rows of a block, blocks of a table at least, and pairs that are compared at once.
BLOCK, LEAST_BLOCKS, CELLS = 16_384, 6, 1 << 20
#: Rows of a batch that comes out, and edges that a forest is made of at once.
OUT_ROWS, EDGES = 100_000, 2_000_000
_LOW, _HIGH = np.uint64(0x7F7F7F7F7F7F7F7F), np.uint64(0x8080808080808080)


def _blocks(n: int, block: int) -> int:
    return max(LEAST_BLOCKS, -(-n // block))


def meet(
    x: DataFrame, y: DataFrame | None, run: Callable[[pa.Table, pa.Table | None], pa.Table | Iterator[pa.Table]], schema: str, block: int = BLOCK,
    keep: Callable[[DataFrame, int], DataFrame] | None = None,
) -> DataFrame:
    """run(part of x, part of y) for all pairs of blocks of two tables with the same columns.

    Without y, x meets itself: run gets two blocks of it, or one and None, whose rows meet each other. It may give
    several tables, one after the other. keep(rows, groups) can store the rows dealt by (i, j) and read them back.
    """
    itself = y is None
    x = materialize(x, "blocks")
    n = _blocks(x.count(), block)
    own = lambda df, k: F.pmod(F.xxhash64(*df.columns), F.lit(k)).cast("int")
    each = lambda k: F.explode(F.sequence(F.lit(0), F.lit(k - 1)))
    if y is None:
        other = x.withColumn("own", own(x, n)).withColumn("other", each(n))
        rows = other.select(F.least("own", "other").alias("i"), F.greatest("own", "other").alias("j"), (F.col("own") > F.col("other")).alias("right"), *x.columns)
        groups = n * (n + 1) // 2
    else:
        y = materialize(y, "blocks")
        k = _blocks(y.count(), block)
        one = x.withColumn("i", own(x, n)).withColumn("j", each(k)).withColumn("right", F.lit(False))
        two = y.withColumn("j", own(y, k)).withColumn("i", each(n)).withColumn("right", F.lit(True))
        rows = one.unionByName(two)
        groups = n * k

    def compare(key: tuple[pa.Scalar, ...], batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        table = pa.Table.from_batches(batches)
        right = table.column("right").to_numpy()
        table = table.drop_columns(["i", "j", "right"])
        alone = itself and key[0].as_py() == key[1].as_py()
        found = run(table.filter(pa.array(~right)), None if alone else table.filter(pa.array(right)))
        for part in [found] if isinstance(found, pa.Table) else found:
            yield from part.to_batches(max_chunksize=OUT_ROWS)

    dealt = keep(rows, groups) if keep else rows.repartition(groups, "i", "j")
    return dealt.groupBy("i", "j").applyInArrow(compare, schema)


def column(table: pa.Table, name: str) -> np.ndarray:
    return table.column(name).to_numpy()


def _steps(rows: np.ndarray, width: int) -> Iterator[np.ndarray]:
    step = max(1, CELLS // max(width, 1))
    yield from (rows[at : at + step] for at in range(0, len(rows), step))


# ---- codes of two halves

#: The fine code of a token that is left out; with it, fine codes are below it.
MARK = 64


def packed(codes: DataFrame, m: int, *more: str | Column) -> DataFrame:
    """(c1, c2, f0, f1, ...): the fine codes of each half, one byte each, in one number of up to eight; values are below 128."""
    if m // 2 > 8 or m % 2:
        raise ValueError("halves of up to 8 positions")
    half = lambda lo, hi: sum((F.shiftleft(F.get("fine", F.lit(p)).cast("long"), 8 * (p - lo)) for p in range(lo, hi)), F.lit(0).cast("long"))
    return codes.select("c1", F.coalesce("c2", "c1").alias("c2"), half(0, m // 2).alias("f0"), half(m // 2, m).alias("f1"), *more)


def code_hits(x: pa.Table, y: pa.Table | None, m: int, marked: bool = False) -> Iterator[tuple[np.ndarray, np.ndarray, np.ndarray]]:
    """(rows of x, rows of y, hits of each with each), over all pairs with a coarse code in common; each pair is in one matrix, elsewhere it has 0.

    Without y a pair of rows of x counts once. marked: fine codes of MARK equal none, not even each other.
    """
    a = [column(x, c) for c in ("c1", "c2", "f0", "f1")]
    b = a if y is None else [column(y, c) for c in ("c1", "c2", "f0", "f1")]
    fine = [(p.astype(np.int64).view(np.uint64), q.astype(np.int64).view(np.uint64)) for p, q in zip(a[2:], b[2:], strict=True)]
    if marked:
        fine = [(p, q | q >> np.uint64(6) & np.uint64(0x0101010101010101)) for p, q in fine]

    def equal(h: int, r: np.ndarray, c: np.ndarray) -> np.ndarray:
        apart = fine[h][0][r][:, None] ^ fine[h][1][c][None, :]
        apart += _LOW
        apart &= _HIGH
        return np.uint8(m // 2) - np.bitwise_count(apart)

    for h in (0, 1):
        for value in np.intersect1d(a[h], b[h]):
            cols = np.flatnonzero(b[h] == value)
            for rows in _steps(np.flatnonzero(a[h] == value), len(cols)):
                hits = equal(h, rows, cols)
                same = a[1 - h][rows][:, None] == b[1 - h][cols][None, :]
                if h == 0:
                    if same.any():
                        hits += np.where(same, equal(1, rows, cols), 0).astype(np.uint8)
                else:
                    hits[same] = 0
                if y is None:
                    hits[rows[:, None] >= cols[None, :]] = 0
                yield rows, cols, hits


def _counted(found: Iterator[tuple], wx: np.ndarray, wy: np.ndarray, wanted: Callable, top: int) -> pa.Table:
    total = np.zeros(top + 1)
    for rows, cols, s in found:
        r, c = np.nonzero(wanted(s))
        total += np.bincount(s[r, c], weights=wx[rows[r]].astype(float) * wy[cols[c]], minlength=top + 1)
    at = np.flatnonzero(total)
    return pa.table({"s": pa.array(at, pa.int64()), "n": pa.array(total[at].astype(np.int64))})


def _with_copies(classes: DataFrame, met: DataFrame, s: int) -> DataFrame:
    """Pairs by s, and those within classes of n equal codes."""
    inside = classes.select(F.lit(s).cast("long").alias("s"), F.expr("n * (n - 1) DIV 2").alias("n"))
    return met.unionAll(inside).groupBy("s").agg(F.sum("n").alias("n")).where("n > 0")


def _subsets(places: range, least: int) -> list[tuple[int, int]]:
    """(size, mask of the bytes) of the sets of at least so many places that hold the first one."""
    first, *more = places
    found = [(1, 0xFF << 8 * first)]
    for p in more:
        found += [(size + 1, mask | 0xFF << 8 * p) for size, mask in found]
    return [f for f in found if f[0] >= least]


def half_counts(classes: DataFrame, half: int, min_hits: int) -> DataFrame:
    """(s, n): how many pairs of ids have equal coarse codes and s >= min_hits equal fine codes in one half, less those with both coarse codes equal; negative and positive parts, to be added up by s.

    For each set of places the pairs that are equal on all of them are those within groups of equal codes.
    Added up over the sets of j places they count a pair with s hits C(s, j) times, which is solved for
    the numbers of pairs. No pair is made; work grows with the items, not with their pairs.
    """
    sides = []
    for sign, cells, f in ((1, ("c1", F.lit(-1)), "f0"), (1, ("c2", F.lit(-1)), "f1"), (-1, ("c1", "c2"), "f0"), (-1, ("c1", "c2"), "f1")):
        c, other = (F.col(x) if isinstance(x, str) else x for x in cells)
        rows = classes.select(c.alias("c"), other.alias("o"), F.lit(int(f[1])).alias("h"), F.lit(sign).alias("sign"), F.col(f).alias("f"), "n")
        sides.append(rows.groupBy("c", "o", "h", "sign", "f").agg(F.sum("n").alias("n")))
    rows = sides[0]
    for x in sides[1:]:
        rows = rows.unionAll(x)
    starts = [p for p in range(half) if half - p >= min_hits]
    if not starts:
        return classes.select(F.lit(0).cast("long").alias("s"), F.lit(0).cast("long").alias("n")).limit(0)
    rows = rows.withColumn("p", F.explode(F.array(*map(F.lit, starts))))
    value = F.expr("shiftright(f, 8 * p)").bitwiseAND(F.lit(7))
    rows = rows.withColumn("v", F.when(F.col("sign") > 0, value).otherwise(0).cast("int"))

    def run(key: tuple[pa.Scalar, ...], batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        table = pa.Table.from_batches(batches)
        f, n, p = column(table, "f").astype(np.int64).view(np.uint64), column(table, "n"), key[4].as_py()
        moments = np.zeros(half + 1, np.int64)
        for size, mask in _subsets(range(p, half), min_hits):
            code = f & np.uint64(mask)
            order = np.argsort(code)
            code = code[order]
            inside = np.add.reduceat(n[order], np.flatnonzero(np.r_[True, code[1:] != code[:-1]]))
            moments[size] += (inside * (inside - 1) // 2).sum()
        at = np.flatnonzero(moments)
        yield pa.RecordBatch.from_arrays([pa.array(at.astype(np.int32)), pa.array(moments[at] * key[3].as_py())], names=["j", "n"])

    moments = rows.groupBy("c", "o", "h", "sign", "p", "v").applyInArrow(run, "j int, n long").groupBy("j").agg(F.sum("n").alias("n"))
    terms = F.array(*(F.struct(F.lit(j).alias("j"), F.lit(s).cast("long").alias("s"), F.lit((-1) ** (j - s) * comb(j, s)).cast("decimal(8,0)").alias("k")) for j in range(min_hits, half + 1) for s in range(min_hits, j + 1)))
    solved = moments.withColumn("t", F.explode(F.filter(terms, lambda t: t["j"] == F.col("j"))))
    return solved.groupBy(F.col("t.s").alias("s")).agg(F.sum(F.col("n").cast("decimal(20,0)") * F.col("t.k")).cast("long").alias("n"))


def cell_counts(classes: DataFrame, m: int, min_hits: int) -> DataFrame:
    """(s, n): how many pairs of ids of different codes with both coarse codes equal have s >= min_hits equal tokens; block against block within each cell."""
    sizes = classes.groupBy("c1", "c2").agg(F.ceil(F.count(F.lit(1)) / BLOCK).cast("int").alias("blocks"))
    own = classes.join(sizes, ["c1", "c2"]).withColumn("own", F.pmod(F.xxhash64("f0", "f1"), F.col("blocks")).cast("int"))
    other = own.withColumn("other", F.explode(F.sequence(F.lit(0), F.col("blocks") - 1)))
    rows = other.select("c1", "c2", F.least("own", "other").alias("i"), F.greatest("own", "other").alias("j"), (F.col("own") > F.col("other")).alias("right"), "f0", "f1", "n")

    def run(key: tuple[pa.Scalar, ...], batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        table = pa.Table.from_batches(batches)
        right = column(table, "right")
        f = [column(table, c).astype(np.int64).view(np.uint64) for c in ("f0", "f1")]
        n, alone = column(table, "n"), key[2].as_py() == key[3].as_py()
        x = np.flatnonzero(~right)
        y = x if alone else np.flatnonzero(right)

        def found():
            for rows in _steps(np.arange(len(x)), len(y)):
                hits = np.full((len(rows), len(y)), m, np.uint8)
                for half in f:
                    apart = half[x[rows]][:, None] ^ half[y][None, :]
                    apart += _LOW
                    apart &= _HIGH
                    hits -= np.bitwise_count(apart)
                if alone:
                    hits[rows[:, None] >= np.arange(len(y))[None, :]] = 0
                yield rows, np.arange(len(y)), hits

        yield from _counted(found(), n[x], n[y], lambda s: s >= min_hits, m).to_batches()

    return rows.groupBy("c1", "c2", "i", "j").applyInArrow(run, "s long, n long")


def count_hits(codes: DataFrame, m: int, min_hits: int) -> DataFrame:
    """(s, n): how many pairs of ids have s equal tokens of m, for s >= min_hits >= 1.

    Pairs with one coarse code in common are counted without being made (half_counts); the few with both are compared, equal codes once.
    """
    classes = materialize(packed(codes, m, "id").groupBy("c1", "c2", "f0", "f1").agg(F.countDistinct("id").alias("n")), "classes")
    return _with_copies(classes, half_counts(classes, m // 2, min_hits).unionAll(cell_counts(classes, m, min_hits)), m)


def hit_pairs(codes: DataFrame, m: int, min_hits: int, keep: Callable[[DataFrame, int], DataFrame] | None = None) -> DataFrame:
    """(a, b, hits), a < b, of the items with min_hits >= 1 or more equal tokens of m."""

    def run(x, y):
        own, other = column(x, "id"), column(x if y is None else y, "id")
        for rows, cols, hits in code_hits(x, y, m):
            r, c = np.nonzero(hits >= min_hits)
            a, b = own[rows[r]], other[cols[c]]
            p = np.c_[np.minimum(a, b), np.maximum(a, b), hits[r, c].astype(np.int64)][a != b]
            if len(p):
                yield pa.table({"a": p[:, 0], "b": p[:, 1], "hits": p[:, 2]})

    return meet(packed(codes, m, "id"), None, run, "a long, b long, hits long", keep=keep)


def spanning(u: np.ndarray, v: np.ndarray, w: np.ndarray, n: int) -> np.ndarray:
    """Places of a spanning forest of greatest weights among edges of the nodes 0 to n - 1.

    For any bound, its edges of more than that connect what all such edges connect. Each round ties
    every root that has a smaller neighbour to one, by one edge.
    """
    root, chosen = np.arange(n), [np.empty(0, np.int64)]
    for level in np.unique(w)[::-1]:
        e = np.flatnonzero(w == level)
        while True:
            a, b = root[u[e]], root[v[e]]
            apart = a != b
            e, a, b = e[apart], a[apart], b[apart]
            if not len(e):
                break
            last = np.full(n, -1)
            last[np.maximum(a, b)] = np.arange(len(e))
            tied = np.flatnonzero(last >= 0)
            by = last[tied]
            chosen.append(e[by])
            root[tied] = np.minimum(a, b)[by]
            while (root != (up := root[root])).any():
                root = up
    return np.concatenate(chosen)


def hit_forests(codes: DataFrame, m: int, min_hits: int, block: int = 2 * BLOCK) -> tuple[DataFrame, DataFrame]:
    """(s, n): how many pairs of ids have s >= min_hits equal tokens of m; and edges (a, b, s) that connect, above each s, what these pairs connect.

    Tokens with the fine code MARK equal none. Of each pair of blocks only a spanning forest comes
    out, so the edges grow with the items of a block, not with its pairs; items of equal codes are one class.
    """
    code = ["c1", "c2", "f0", "f1"]
    marks = lambda c: F.bit_count(F.col(c).bitwiseAND(F.lit(int.from_bytes(bytes([MARK] * 8)))))
    own = materialize(packed(codes, m, "id").withColumn("s", (m - marks("f0") - marks("f1")).cast("long")).where(F.col("s") >= min_hits), "marked")
    classes = materialize(own.groupBy(*code, "s").agg(F.min("id").alias("id"), F.countDistinct("id").alias("n")), "classes")

    def run(x, y):
        z = x if y is None else y
        ids, wx, wz = np.r_[column(x, "id"), column(z, "id")], column(x, "n").astype(float), column(z, "n")
        total, parts, held = np.zeros(m + 1), [], 0
        first = 0 if y is None else len(x)

        def forest():
            u, v, s = (np.concatenate(p) for p in zip(*parts, strict=True))
            at = spanning(u, v, s, len(x) + len(z))
            return u[at], v[at], s[at]

        for rows, cols, hits in code_hits(x, y, m, marked=True):
            r, c = np.nonzero(hits >= min_hits)
            u, v, s = rows[r], cols[c], hits[r, c]
            total += np.bincount(s, weights=wx[u] * wz[v], minlength=m + 1)
            parts.append((u, v + first, s))
            held += len(s)
            if held > EDGES:
                parts = [forest()]
                held = len(parts[0][0])
        at = np.flatnonzero(total)
        yield pa.table({"a": pa.nulls(len(at), pa.int64()), "b": pa.nulls(len(at), pa.int64()), "s": pa.array(at, pa.int64()), "n": pa.array(total[at].astype(np.int64))})
        if held:
            u, v, s = forest()
            yield pa.table({"a": ids[u], "b": ids[v], "s": s.astype(np.int64), "n": pa.nulls(len(s), pa.int64())})

    found = materialize(meet(classes.select(*code, "id", "n"), None, run, "a long, b long, s long, n long", block), "forests")
    inside = classes.select("s", F.expr("n * (n - 1) DIV 2").alias("n"))
    counts = found.where("n IS NOT NULL").select("s", "n").unionAll(inside).groupBy("s").agg(F.sum("n").alias("n")).where("n > 0")
    many = classes.where("n > 1").select(*code, F.col("id").alias("a"))
    same = own.join(many, code).where("id <> a").select("a", F.col("id").alias("b"), "s").distinct()
    return counts, found.where("n IS NULL").select("a", "b", "s").unionAll(same)


# ---- binary codes


def bit_distances(x: pa.Table, y: pa.Table | None, words: int) -> Iterator[tuple[np.ndarray, np.ndarray, np.ndarray]]:
    """(rows of x, rows of y, Hamming distances); without y, 255 where a pair of rows of x has been or is no pair. At most 254 bits."""
    a = [column(x, f"w{i}").view(np.uint64) for i in range(words)]
    b = a if y is None else [column(y, f"w{i}").view(np.uint64) for i in range(words)]
    every = np.arange(len(b[0]))
    for rows in _steps(np.arange(len(a[0])), len(every)):
        cols = every[rows[0] :] if y is None else every
        d = np.zeros((len(rows), len(cols)), np.uint8)
        for p, q in zip(a, b, strict=True):
            d += np.bitwise_count(p[rows][:, None] ^ q[cols][None, :])
        if y is None:
            d[rows[:, None] >= cols[None, :]] = 255
        yield rows, cols, d


def _wide(bits: int) -> tuple[int, list[Column]]:
    """(words, columns): words of 32 bits as numbers of 64."""
    if bits > 254:
        raise ValueError("at most 254 bits")
    n = -(-bits // 32)
    word = lambda i: F.coalesce(F.get("words", F.lit(i)), F.lit(0).cast("long")) if i < n else F.lit(0).cast("long")
    return -(-n // 2), [word(i).bitwiseOR(F.shiftleft(word(i + 1), 32)).alias(f"w{i // 2}") for i in range(0, n, 2)]


def near_bits(codes: DataFrame, radius: int, bits: int) -> DataFrame:
    """(a, b, dist), a < b, of codes(id, words) within the radius."""
    words, columns = _wide(bits)

    def run(x, y):
        own, other = column(x, "id"), column(x if y is None else y, "id")
        out = [np.empty((0, 3), np.int64)]
        for rows, cols, d in bit_distances(x, y, words):
            r, c = np.nonzero(d <= radius)
            a, b = own[rows[r]], other[cols[c]]
            out.append(np.c_[np.minimum(a, b), np.maximum(a, b), d[r, c].astype(np.int64)][a != b])
        p = np.concatenate(out)
        return pa.table({"a": p[:, 0], "b": p[:, 1], "dist": p[:, 2].astype(np.int32)})

    return meet(codes.select("id", *columns), None, run, "a long, b long, dist int")


def count_distances(codes: DataFrame, radius: int, bits: int) -> DataFrame:
    """(s, n): how many pairs of codes(id, words) are s apart, for s up to the radius; equal codes are compared once."""
    words, columns = _wide(bits)
    classes = materialize(codes.select("id", *columns).groupBy(*(f"w{i}" for i in range(words))).agg(F.countDistinct("id").alias("n")), "classes")

    def run(x, y):
        w = column(x, "n")
        return _counted(bit_distances(x, y, words), w, w if y is None else column(y, "n"), lambda s: s <= radius, radius)

    return _with_copies(classes, meet(classes, None, run, "s long, n long"), 0)


# ---- query sets


def pooled_hits(queries: DataFrame, items: DataFrame, m: int) -> DataFrame:
    """(set_id, id, most, reached): of each set's queries the most equal tokens with an item, and how many have one at least.

    queries has (set_id, id, c1, c2, fine), items (id, c1, c2, fine); equal codes are compared once. Items that no query reached are absent.
    """
    code = ["c1", "c2", "f0", "f1"]
    asked = packed(queries, m, "set_id").groupBy("set_id", *code).agg(F.count(F.lit(1)).alias("n"))
    own = materialize(packed(items, m, "id"), "items")
    kinds = own.select(F.lit(None).cast("string").alias("set_id"), *code, F.lit(1).cast("long").alias("n")).distinct()

    def run(x, y):
        sets = y.column("set_id").to_pylist()
        names = list(dict.fromkeys(sets))
        of = np.array([names.index(s) for s in sets], np.int64)
        w = column(y, "n")
        most, reached = np.zeros((len(x), len(names)), np.uint8), np.zeros((len(x), len(names)), np.int64)
        for rows, cols, hits in code_hits(x, y, m):
            for k in range(len(names)):
                mine = of[cols] == k
                if mine.any():
                    h = hits[:, mine]
                    most[rows, k] = np.maximum(most[rows, k], h.max(1))
                    reached[rows, k] += (h > 0) @ w[cols[mine]]
        r, k = np.nonzero(reached)
        part = x.select(code).take(pa.array(r))
        return pa.table({"set_id": pa.array([names[i] for i in k], pa.string()), **{c: part.column(c) for c in code}, "most": pa.array(most[r, k].astype(np.int64)), "reached": pa.array(reached[r, k])})

    kind = "set_id string, c1 int, c2 int, f0 long, f1 long, most long, reached long"
    best = meet(kinds, asked, run, kind).groupBy("set_id", *code).agg(F.max("most").alias("most"), F.sum("reached").alias("reached"))
    return best.join(own, code).select("set_id", "id", "most", "reached")
