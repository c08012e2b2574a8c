"""Benchmark decontamination by winnowing, in DataFrame functions only.

Documents and items become words, and words 64-bit hashes. Of the hashes of K consecutive
words, the least of each SLIDE consecutive ones is a fingerprint; any shared run of
K + SLIDE - 1 = WINDOW words has a fingerprint in common, wherever it stands. Texts that
share a fingerprint with an item are candidates; in these, every window is compared with
the items' windows, word for word, which extends the hits to all words of all occurrences. Items shorter
than WINDOW are one window of their own length; for them, the grams of the shortest such
length at every place are fingerprints.

Words and fingerprints come from one pass over the texts. Texts are known by two 64-bit hashes;
of copies, those with the smallest doc_id are compared with the items. Windows that many items
share carry the list of these items, and are not multiplied by them.
"""

from __future__ import annotations

from functools import reduce

from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

from codematch.functions.arrays import head, let, lower_ascii, tail, text_key
from codematch.llm.joins import HEAVY, MOST, each_copy, left_join
from codematch.sources.io import materialize

#: Characters between words of a lower-cased text.
_BREAKS = r"[\x00-\x2F\x3A-\x60\x7B-\x7F]+"
WINDOW, K = 10, 5
#: Broadcast fingerprints, windows or candidates only up to this many rows.
BROADCAST_ROWS = 500_000


def words_of(text: Column) -> Column:
    return F.filter(F.split(lower_ascii(F.coalesce(text, F.lit(""))), _BREAKS), lambda w: w != "")


def hashes(words: Column) -> Column:
    return F.transform(words, lambda w: F.xxhash64(w))


def grams(h: Column, k: int) -> Column:
    """Hashes of the runs of k elements; as long as h, with a rest at the end that head() cuts."""
    pair = lambda a, b: F.zip_with(a, b, lambda x, y: F.xxhash64(x, y))

    def step(run: Column, width: int, total: Column | None, done: int, left: int) -> Column:
        if left & 1:
            total = run if total is None else pair(total, tail(run, done))
            done += width
        left >>= 1
        if not left:
            return total
        go_on = lambda t: let(pair(run, tail(run, width)), lambda wide: step(wide, 2 * width, t, done, left))
        return go_on(None) if total is None else let(total, go_on)

    return step(h, 1, None, 0, k)


def fingerprints(h: Column, window: int = WINDOW, k: int = K) -> Column:
    """The distinct least gram hashes of an array of word hashes; none if it is shorter than the window."""
    slide = window - k + 1

    def least(a: Column) -> Column:
        low = lambda x, y: F.zip_with(x, y, lambda p, q: F.least(p, q))

        def widen(x: Column, width: int) -> Column:
            if width == slide:
                return x
            gap = min(width, slide - width)
            return let(low(x, tail(x, gap)), lambda y: widen(y, width + gap))

        return widen(a, 1)

    enough = F.size(h) - (window - 1)
    return F.when(enough > 0, F.array_distinct(head(least(head(grams(h, k), F.size(h) - (k - 1))), enough))).otherwise(F.array().cast("array<bigint>"))


def _maybe_broadcast(df: DataFrame, limit: int = BROADCAST_ROWS) -> DataFrame:
    return F.broadcast(df) if df.count() <= limit else df


def item_windows(items: DataFrame, window: int = WINDOW) -> DataFrame:
    """(item_id, words, h, length) of each item that has an id and a word."""
    words = items.where("item_id IS NOT NULL").select("item_id", let(words_of(F.col("text")), lambda x: x).alias("words"))
    words = words.where(F.size("words") > 0)
    return words.withColumn("h", hashes(F.col("words"))).withColumn("length", F.least(F.size("words"), F.lit(window)))


def windows_at(words: Column, h: Column, n: int) -> Column:
    """(length, s, w, t) of each run of n words: its place, its hash and its words, joined by blanks."""
    run = lambda s: F.array_join(F.slice(words, s + 1, F.lit(n)), " ")
    at = lambda w, s: F.struct(F.lit(n).alias("length"), s.alias("s"), w.alias("w"), run(s).alias("t"))
    return F.transform(head(grams(h, n), F.size(h) - (n - 1)), at)


class Items:
    """Windows and fingerprints of the items, as written tables, and the fingerprints that a document needs to meet them."""

    def __init__(self, items: DataFrame, window: int = WINDOW, k: int = K):
        self.window, self.k = window, k
        items = materialize(item_windows(items.select("item_id", "text"), window), "items")
        self.lengths = sorted(r.length for r in items.select("length").distinct().collect())
        self.short = [n for n in self.lengths if n < window]
        if not self.lengths:
            return
        of = lambda n: items.where(F.col("length") == n).select("item_id", F.explode(windows_at(F.col("words"), F.col("h"), n)).alias("x"))
        each = reduce(DataFrame.unionAll, map(of, self.lengths)).select("item_id", "x.length", "x.w", "x.t")
        ids = F.array_sort(F.collect_set(F.col("item_id").cast("string"))).alias("item_ids")
        self.windows = materialize(each.groupBy("length", "w", "t").agg(ids), "windows")
        marks = []
        if window in self.lengths:
            marks.append(items.where(F.col("length") == window).select(F.explode(fingerprints(F.col("h"), window, k)).alias("f")))
        if self.short:
            runs = head(grams(F.col("h"), self.short[0]), F.size("h") - (self.short[0] - 1))
            marks.append(items.where(F.col("length") < window).select(F.explode(runs).alias("f")))
        self.marks = materialize(reduce(DataFrame.unionAll, marks).distinct(), "marks")

    def marks_of(self, h: Column) -> Column:
        """Fingerprints of a document's word hashes."""
        out = fingerprints(h, self.window, self.k) if self.window in self.lengths else None
        if self.short:
            few = F.array_distinct(head(grams(h, self.short[0]), F.size(h) - (self.short[0] - 1)))
            out = few if out is None else F.array_union(out, few)
        return out


def marked_documents(docs: DataFrame, items: Items) -> DataFrame:
    """(doc_id, h1, h2, n_words, copies, met) of docs(doc_id, text): a row for each pair of doc_id and text, with the number of its rows.

    met: a fingerprint of the text is one of an item's. One pass over the texts; the
    fingerprints are joined with those of the items, and counted back where they lie.
    """
    h1, h2 = text_key(F.col("text"))
    both = lambda h: F.struct(F.size(h).cast("long").alias("n_words"), items.marks_of(h).alias("f"))
    rows = docs.select("doc_id", h1.alias("h1"), h2.alias("h2"), let(hashes(words_of(F.col("text"))), both).alias("x"))
    each = rows.select("doc_id", "h1", "h2", "x.n_words", F.posexplode_outer("x.f").alias("at", "f"))
    known = items.marks.select(F.col("f").alias("mark"))
    joined = each.join(_maybe_broadcast(known), F.col("f") == F.col("mark"), "left")
    copies = F.count_if(F.coalesce(F.col("at"), F.lit(0)) == 0).alias("copies")
    return joined.groupBy("doc_id", "h1", "h2", "n_words").agg(copies, F.max(F.col("mark").isNotNull()).alias("met"))


def contaminated_words(docs: DataFrame, items: Items, marked: DataFrame) -> DataFrame:
    """One row per distinct contaminated text: h1, h2, spans (array of start, end in words), item_ids (sorted as strings).

    marked: of marked_documents, written.
    """
    if not items.lengths:
        return docs.sparkSession.createDataFrame([], "h1 long, h2 long, spans array<struct<s:int,e:int>>, item_ids array<string>")
    few = marked.where("met").groupBy(F.col("h1").alias("m1"), F.col("h2").alias("m2")).agg(F.min("doc_id").alias("rep"))
    few = materialize(few, "candidates")
    h1, h2 = text_key(F.col("text"))
    own = (F.col("h1") == F.col("m1")) & (F.col("h2") == F.col("m2")) & F.col("doc_id").eqNullSafe(F.col("rep"))
    near = docs.select("doc_id", "text", h1.alias("h1"), h2.alias("h2")).join(_maybe_broadcast(few), own, "left_semi")
    places = lambda w: let(hashes(w), lambda h: F.concat(*(windows_at(w, h, n) for n in items.lengths)))
    found = near.select("h1", "h2", F.explode(let(words_of(F.col("text")), places)).alias("x")).select("h1", "h2", "x.*")
    hits = found.join(_maybe_broadcast(items.windows), ["length", "w", "t"])
    hits = hits.select("h1", "h2", F.struct(F.col("s"), (F.col("s") + F.col("length")).alias("e")).alias("span"), "item_ids")
    of_text = F.array_sort(F.array_distinct(F.flatten(F.collect_set("item_ids")))).alias("item_ids")
    return hits.groupBy("h1", "h2").agg(F.array_sort(F.collect_set("span")).alias("spans"), of_text)


def covered(spans: Column) -> Column:
    """Number of places inside sorted spans, each counted once."""
    start = F.struct(F.lit(0).alias("upto"), F.lit(0).cast("long").alias("n"))
    new = lambda a, x: F.greatest(x.e - F.greatest(x.s, a.upto), F.lit(0))
    step = lambda a, x: F.struct(F.greatest(a.upto, x.e).alias("upto"), (a.n + new(a, x)).alias("n"))
    return F.aggregate(spans, start, step, lambda a: a.n)


def contamination(docs: DataFrame, items: DataFrame, window: int = WINDOW, k: int = K, most: int = MOST, heavy: int = HEAVY) -> DataFrame:
    """The rows of docs(doc_id, text) with n_words, n_hit, n_items, items_sha256 and contaminated.

    Null and empty texts have no words and no hits. Items without id or words are left out;
    an id that several rows have is one item with the windows of all. Repeated documents each
    get a row. Other columns of either table are ignored. most and heavy are the limits of the
    join of hits to documents (joins.left_join).
    """
    docs = docs.select("doc_id", F.col("text").cast("string").alias("text"))
    known = Items(items, window, k)
    zero = F.lit(0).cast("long")
    none = F.array().cast("array<string>")
    if known.lengths:
        marked = materialize(marked_documents(docs, known), "marked")
        hits = contaminated_words(docs, known, marked)
        digest = F.sha2(F.array_join("item_ids", ","), 256)
        keys, counts = (F.col("h1").alias("k1"), F.col("h2").alias("k2")), (covered(F.col("spans")).alias("n_hit"), F.size("item_ids").cast("long").alias("n_items"))
        per = hits.select(*keys, *counts, digest.alias("items_sha256"))
        held = marked.where("met").groupBy(F.col("h1").alias("c1"), F.col("h2").alias("c2")).agg(F.sum("copies").alias("held"))
        per = materialize(per.join(held, (F.col("k1") == F.col("c1")) & (F.col("k2") == F.col("c2"))).drop("c1", "c2"), "hits")
        met = left_join(marked.where("met"), per, {"h1": "k1", "h2": "k2"}, size="held", found="n_hit", most=most, heavy=heavy)
        bare = marked.where("NOT met").withColumns({"n_hit": zero, "n_items": zero, "items_sha256": F.lit(None).cast("string")})
        out = each_copy(met, "copies").unionByName(each_copy(bare, "copies"))
    else:
        n_words = F.size(words_of(F.col("text"))).cast("long").alias("n_words")
        out = docs.select("doc_id", n_words, zero.alias("n_hit"), zero.alias("n_items"), F.lit(None).cast("string").alias("items_sha256"))
    n_hit = F.coalesce("n_hit", zero)
    empty = F.sha2(F.array_join(none, ","), 256)
    items_of = (F.coalesce("n_items", zero).alias("n_items"), F.coalesce("items_sha256", empty).alias("items_sha256"))
    return out.select("doc_id", "n_words", n_hit.alias("n_hit"), *items_of, (n_hit > 0).alias("contaminated"))


def clean_documents(docs: DataFrame, items: DataFrame, window: int = WINDOW, k: int = K) -> DataFrame:
    """The rows of docs(doc_id, text, ...), with all columns, that hold no window of an item; null and empty texts hold none."""
    known = Items(items, window, k)
    if not known.lengths:
        return docs
    plain = docs.select("doc_id", F.col("text").cast("string").alias("text"))
    marked = materialize(marked_documents(plain, known), "marked")
    hits = materialize(contaminated_words(plain, known, marked).select(F.col("h1").alias("k1"), F.col("h2").alias("k2")), "hits")
    h1, h2 = text_key(F.col("text").cast("string"))
    return docs.join(_maybe_broadcast(hits), (h1 == F.col("k1")) & (h2 == F.col("k2")), "left_anti")
