"""Language identification by Bayesian fusion of evidence.

Four kinds of evidence meet in one posterior: how likely a text is under each language's
byte trigrams; the language that its markup or its metadata declare; the suffix of its
address; and a prior of its host. The prior is hierarchical: counts of a host are smoothed
by those of its address suffix, and these by those of the corpus, all from grouped
aggregation over every row. A text weighs as much as its number of trigrams, up to a bound,
so a few letters don't outvote the other evidence.

The trigram tables are learnt from all distinct texts, by the languages they declare.
"""

from __future__ import annotations

import re
from collections.abc import Iterator
from dataclasses import dataclass

import numpy as np
import pyarrow as pa
from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

from codematch.functions.arrays import text_key
from codematch.llm.joins import left_join
from codematch.llm.workers import give_back, released
from codematch.sources.io import discard, materialize

GRAMS = 1 << 14
#: Trigram counts travel in slices of so many.
SLICE = 1024
#: Rows that a parent's share counts for, in the prior of a host or suffix.
STRENGTH = 20.0
#: How likely a declared language or a country's suffix is the right one.
DECLARED, SUFFIX = 0.9, 0.7
#: Text evidence counts as that of so many independent grams at most.
EFFECTIVE = 60.0
#: A text is no language if its grams are less likely than even ones, or the best is less probable than this.
LEAST = 0.5
#: Broadcast the texts that have copies only up to this many.
BROADCAST_COPIES = 200_000
# Suffixes of countries with one main language.
SUFFIXES = {"de": "de", "at": "de", "fr": "fr", "es": "es", "mx": "es", "ar": "es", "uk": "en", "us": "en", "au": "en", "ie": "en", "it": "it", "pt": "pt", "br": "pt", "nl": "nl", "pl": "pl"}
_HIDDEN = re.compile(r"<(script|style)\b.*?</\1\s*>|<!--.*?-->", re.S | re.I)
_TAG = re.compile(r"<[^>]*>")
_LUT = np.full(256, 32, np.uint8)
_LUT[97:123] = np.arange(97, 123)
_LUT[65:91] = np.arange(97, 123)
_LUT[128:] = np.arange(128, 256)


def visible_text(html: str | None) -> str:
    """Text of a page without scripts, styles, comments and tags."""
    return _TAG.sub(" ", _HIDDEN.sub(" ", html)) if html else ""


def gram_places(text: bytes | None) -> np.ndarray:
    """Hashed byte trigrams of a text, letters only; those with two blanks or more are left out."""
    if not text:
        return np.empty(0, np.int64)
    b = _LUT[np.frombuffer(b" " + text + b" ", np.uint8)]
    b = b[np.r_[True, (b[1:] != 32) | (b[:-1] != 32)]].astype(np.uint32)
    if len(b) < 3:  # blanks only
        return np.empty(0, np.int64)
    code = b[:-2] * np.uint32(0x9E3779B1) + b[1:-1] * np.uint32(0x85EBCA6B) + b[2:] * np.uint32(0xC2B2AE35)
    code ^= code >> np.uint32(15)
    code *= np.uint32(0x2C1B3C6D)
    return (code >> np.uint32(32 - GRAMS.bit_length() + 1)).astype(np.int64)


@dataclass
class Profiles:
    """languages, and the log probability of each gram in each: GRAMS rows."""

    languages: list[str]
    table: np.ndarray

    def evidence(self, text: bytes | None) -> list[float]:
        """Mean log likelihood of a text's grams above even ones, by language, and their number; empty without grams."""
        places = gram_places(text)
        if not len(places):
            return []
        if len(places) < 4 * GRAMS:
            mean = self.table[places].mean(0)
        else:
            mean = np.bincount(places, minlength=GRAMS) @ self.table / len(places)
        return [*(mean + np.log(GRAMS)).tolist(), float(len(places))]


def normal_language(c: Column) -> Column:
    """en for en-US, EN_gb and en."""
    out = F.lower(F.regexp_extract(F.coalesce(c.cast("string"), F.lit("")), r"^\s*([A-Za-z]{2,3})(?:[-_].*)?\s*$", 1))
    return F.when(out != "", out)


def learn(texts: DataFrame, least_rows: int = 10) -> Profiles:
    """Trigram tables from all rows of texts(text, declared); copies of a text in a language count once.

    A language takes part if least_rows rows declare it (or a twentieth of all, if that is
    less), at every size.
    """
    h1, h2 = text_key(F.col("text"))
    known = texts.where("declared IS NOT NULL AND length(text) > 0").select("declared", "text", h1.alias("h1"), h2.alias("h2"))
    copies = materialize(known.groupBy("declared", "h1", "h2").agg(F.count(F.lit(1)).alias("n")), "declared-texts")
    rows = {r.declared: r.n for r in copies.groupBy("declared").agg(F.sum("n").alias("n")).collect()}
    languages = sorted(x for x in rows if rows[x] >= min(least_rows, max(1, sum(rows.values()) // 20))) or ["und"]
    more = copies.where("n > 1").select(F.col("declared").alias("d"), F.col("h1").alias("k1"), F.col("h2").alias("k2"), "n")
    more = F.broadcast(more) if more.limit(BROADCAST_COPIES + 1).count() <= BROADCAST_COPIES else more
    each = known.where(F.col("declared").isin(languages)).join(more, (F.col("declared") == F.col("d")) & (F.col("h1") == F.col("k1")) & (F.col("h2") == F.col("k2")), "left")

    def count(batches) -> Iterator[pa.RecordBatch]:
        total: dict[str, np.ndarray] = {}
        for batch in batches:
            for at in range(0, batch.num_rows, 256):
                part = batch.slice(at, 256)
                for language, text, n in zip(part.column(0).to_pylist(), part.column(1).cast(pa.binary()).to_pylist(), part.column(2).to_pylist(), strict=True):
                    if language not in total:
                        total[language] = np.zeros(GRAMS)
                    places = gram_places(text)
                    if len(places) < GRAMS // 8:
                        np.add.at(total[language], places, 1 / n)
                    else:
                        total[language] += np.bincount(places, minlength=GRAMS) / n
        for language, counts in total.items():
            yield _slices([(language, i, x) for i, x in enumerate(counts.reshape(-1, SLICE))])

    def add(batches) -> Iterator[pa.RecordBatch]:
        total: dict[tuple[str, int], np.ndarray] = {}
        for batch in batches:
            for language, i, counts in zip(*(c.to_pylist() for c in batch.columns), strict=True):
                total[language, i] = total.get((language, i), 0) + np.frombuffer(counts)
        yield _slices([(*k, x) for k, x in total.items()])

    schema = "language string, slice int, counts binary"
    parts = each.select("declared", "text", F.coalesce("n", F.lit(1)).alias("n")).mapInArrow(released(count), schema)
    counts = np.zeros((len(languages), GRAMS))
    place = {x: i for i, x in enumerate(languages)}
    for r in parts.repartition(16, "language", "slice").mapInArrow(released(add), schema).collect():
        counts[place[r.language], r.slice * SLICE : (r.slice + 1) * SLICE] += np.frombuffer(bytes(r.counts))
    discard(copies)
    counts = np.rint(counts) + 0.2  # copies add up to one but for rounding
    return Profiles(languages, np.ascontiguousarray(np.log(counts / counts.sum(1, keepdims=True)).T.astype(np.float32)))


def _slices(rows: list[tuple[str, int, np.ndarray]]) -> pa.RecordBatch:
    return pa.RecordBatch.from_pydict({"language": pa.array([r[0] for r in rows], pa.string()), "slice": pa.array([r[1] for r in rows], pa.int32()), "counts": pa.array([r[2].astype(float).tobytes() for r in rows], pa.binary())})


def text_evidence(profiles: Profiles, text: Column) -> Column:
    @F.arrow_udf("array<double>")
    def of(texts: pa.Array) -> pa.Array:
        out = pa.array([profiles.evidence(x) for at in range(0, len(texts), 256) for x in texts.slice(at, 256).cast(pa.binary()).to_pylist()], pa.list_(pa.float64()))
        give_back()
        return out

    return of(text)


def _host_counts(rows: DataFrame, languages: int) -> DataFrame:
    """(suffix, host, n0, n1, ...): rows of each host by language; rows: suffix, host, top (place of the likeliest language by text, or null)."""
    return rows.where("top IS NOT NULL").groupBy("suffix", "host").agg(*(F.sum((F.col("top") == i).cast("long")).alias(f"n{i}") for i in range(languages)))


def _host_table(per: DataFrame, languages: int) -> tuple[DataFrame, list[float]]:
    """Log prior of each (suffix, host) of _host_counts, as an array by language, with the number of its rows; and that of the corpus."""
    names = [f"n{i}" for i in range(languages)]
    by_suffix = per.groupBy(F.col("suffix").alias("zone")).agg(*(F.sum(n).alias(f"s_{n}") for n in names))
    whole = per.agg(*(F.coalesce(F.sum(n), F.lit(0)).alias(n) for n in names)).first()
    base = np.array([whole[n] for n in names], float) + 1
    base = base / base.sum()
    total = lambda prefix: sum((F.col(f"{prefix}{n}") for n in names), F.lit(0))
    suffix_share = [(F.col(f"s_{n}") + STRENGTH * float(p)) / (total("s_") + STRENGTH) for n, p in zip(names, base, strict=True)]
    joined = per.join(by_suffix, per.suffix.eqNullSafe(by_suffix.zone))
    share = [(F.col(n) + STRENGTH * s) / (total("") + STRENGTH) for n, s in zip(names, suffix_share, strict=True)]
    return joined.select(F.col("suffix").alias("lid_zone"), F.col("host").alias("lid_place"), F.array(*(F.log(x) for x in share)).alias("lid_prior"), total("").alias("lid_rows")), [float(x) for x in np.log(base)]


def identify(
    rows: DataFrame, text: str = "text", declared: Column | None = None, suffix: Column | None = None, host: Column | None = None,
    profiles: Profiles | None = None, keep: list[str] | None = None,
) -> DataFrame:
    """rows with lid_language, lid_probability and lid_accepted.

    Evidence that is null says nothing. A row is rejected if its text has no grams, if its
    best language explains them worse than even chances, or if the best posterior is under
    LEAST; lid_language is then the best guess, null without grams. Repeated rows get equal
    results. Columns that begin with lid_ are replaced. keep names the columns of rows to
    return, by default all. The evidence of the texts is computed once and written, with
    these columns, to the shared folder.
    """
    none = F.lit(None).cast("string")
    rows = rows.drop(*(c for c in rows.columns if c.startswith("lid_")))
    keep = rows.columns if keep is None else keep
    body = F.col(text).cast("string")
    evidence = {"lid_declared": normal_language(declared if declared is not None else none), "lid_suffix": suffix if suffix is not None else none, "lid_host": host if host is not None else none}
    marked = rows.withColumns(evidence)
    profiles = profiles or learn(marked.select(body.alias("text"), F.col("lid_declared").alias("declared")))
    languages = profiles.languages
    k = len(languages)
    work = materialize(marked.withColumn("lid_grams", text_evidence(profiles, body)).select(*keep, *evidence, "lid_grams"), "evidence")
    lines = F.slice("lid_grams", 1, k)
    work = work.withColumns({"lid_text": lines, "lid_n": F.get("lid_grams", F.lit(k))}).drop("lid_grams")
    top = F.array_position("lid_text", F.array_max("lid_text")).cast("int") - 1
    seen = work.select(F.col("lid_suffix").alias("suffix"), F.col("lid_host").alias("host"), F.when(F.size("lid_text") > 0, top).alias("top"))
    table, base = _host_table(materialize(_host_counts(seen, k), "hosts"), k)
    out = left_join(work, table, {"lid_suffix": "lid_zone", "lid_host": "lid_place"}, size="lid_rows", found="lid_prior")
    others = max(k - 1, 1)
    said = lambda c, right, i: F.when(c == languages[i], F.log(F.lit(right))).when(c.isin(languages), F.log(F.lit((1 - right) / others))).otherwise(F.lit(0.0))
    meant = F.create_map(*(F.lit(x) for kv in SUFFIXES.items() for x in kv))[F.col("lid_suffix")]
    weight = F.least("lid_n", F.lit(EFFECTIVE))
    prior = F.coalesce("lid_prior", F.array(*map(F.lit, base)))
    told = lambda i: F.get("lid_text", F.lit(i)) * weight + F.get(prior, F.lit(i)) + said(F.col("lid_declared"), DECLARED, i) + said(meant, SUFFIX, i)
    out = out.withColumn("lid_logit", F.when(F.size("lid_text") > 0, F.array(*map(told, range(k)))))
    best = F.array_max("lid_logit")
    out = out.withColumn("lid_probability", F.coalesce(1 / F.aggregate("lid_logit", F.lit(0.0), lambda a, x: a + F.exp(x - best)), F.lit(0.0)))
    out = out.withColumn("lid_language", F.get(F.array(*map(F.lit, languages)), F.array_position(F.col("lid_logit"), best).cast("int") - 1))
    ok = (F.size("lid_text") > 0) & (F.array_max("lid_text") > 0) & (F.col("lid_probability") >= LEAST)
    return out.select(*keep, "lid_language", "lid_probability", F.coalesce(ok, F.lit(False)).alias("lid_accepted"))


def documents_and_pages(docs: DataFrame, pages: DataFrame) -> DataFrame:
    """One row per document and per page: doc_id or page_id, lid_language, lid_probability, lid_accepted.

    A document declares its lang and has its source as host. A page declares the lang of its
    html tag; host and suffix come from its url, and its text is what its markup shows.
    """

    @F.arrow_udf("string")
    def shown(html: pa.Array) -> pa.Array:
        out = pa.concat_arrays([pa.array([visible_text(x) for x in html.slice(at, 256).to_pylist()], pa.string()) for at in range(0, len(html), 256)] or [pa.array([], pa.string())])
        give_back()
        return out

    tag = F.regexp_extract(F.coalesce("html", F.lit("")), r"(?i)<html[^>]*\slang\s*=\s*[\"']?([A-Za-z_-]+)", 1)
    address = F.lower(F.regexp_extract(F.coalesce("url", F.lit("")), r"^[A-Za-z][A-Za-z0-9+.-]*://(?:[^/?#@]*@)?([^/?#:@]+)", 1))
    none = F.lit(None).cast("string")
    d = docs.select(F.col("doc_id").cast("long").alias("doc_id"), F.lit(None).cast("long").alias("page_id"), F.col("text").cast("string").alias("text"), F.col("lang").cast("string").alias("tongue"), none.alias("zone"), F.col("source").cast("string").alias("place"))
    p = pages.select(F.lit(None).cast("long").alias("doc_id"), F.col("page_id").cast("long").alias("page_id"), shown(F.col("html")).alias("text"), F.when(tag != "", tag).alias("tongue"), F.when(address != "", F.regexp_extract(address, r"([a-z0-9-]+)\.?$", 1)).alias("zone"), F.when(address != "", address).alias("place"))
    return identify(d.unionAll(p), declared=F.col("tongue"), suffix=F.col("zone"), host=F.col("place"), keep=["doc_id", "page_id"])
