"""Document fingerprints by spot signatures, in DataFrame functions only.

Common words are anchors; an anchor with the chain of the content words that follow it
(common words are skipped) is a signature. Templates hold few common words, prose holds
many, so the set of signatures marks the prose. Sets are compared by Jaccard similarity:
pairs are sought within ranges of set length, by the rarest signatures of each, and a pair
whose lengths alone rule it out is never formed.
"""

from __future__ import annotations

import math

from pyspark.sql import Column, DataFrame, Window
from pyspark.sql import functions as F

from codematch.functions.arrays import let, text_key
from codematch.sources.io import materialize

# Common words of English, German, French and Spanish.
ANCHORS = (
    "the a an of and to in is was that it he for on are with as be this by from or at not",
    "der die das und ist ein eine den dem von zu mit im auf für des sich nicht auch als in war",
    "le la les de des du un une et est en que qui dans pour au sur par avec il elle",
    "el los las del y es un una que se por con para su lo al como más en la de",
)
CHAIN, STRIDE = 2, 1
#: Ranges that the rows are dealt to, for the order of documents.
MOST_RANGES = 2000


def anchor_words() -> list[str]:
    return sorted({w for line in ANCHORS for w in line.split()})


def signatures(text: Column, chain: int = CHAIN, stride: int = STRIDE) -> Column:
    """The sorted set of 64-bit signatures of a text.

    A text with words but no complete chain has one signature, of its word sequence; one
    without words has that of its characters; empty and null texts have none.
    """
    common = anchor_words()
    text = F.coalesce(text, F.lit(""))
    words = F.filter(F.split(F.lower(text), r"[^\p{L}\p{N}]+"), lambda w: w != "")
    reach = (chain - 1) * stride

    def of(w: Column) -> Column:
        places = F.filter(F.transform(w, lambda x, i: F.when(x.isin(common), i).otherwise(F.lit(-1))), lambda i: i >= 0)
        content = F.filter(w, lambda x: ~x.isin(common))

        def chains(c: Column) -> Column:
            # the k-th anchor, at word p, has p - k content words before it
            spot = lambda p, k: F.when(p - k + reach < F.size(c), F.xxhash64(F.get(w, p), *(F.get(c, p - k + j * stride) for j in range(chain))))
            return F.filter(F.transform(places, spot), lambda s: s.isNotNull())

        whole = F.when(F.size(w) > 0, F.array(F.xxhash64(F.lit("words"), F.array_join(w, " ")))).when(text != "", F.array(F.xxhash64(F.lit("characters"), text))).otherwise(F.array().cast("array<bigint>"))
        return let(let(content, chains), lambda s: F.when(F.size(s) > 0, F.sort_array(F.array_distinct(s))).otherwise(whole))

    return let(words, of)


def as_text(sigs: Column) -> Column:
    """The fingerprint as a string: hexadecimal signatures in order."""
    return F.array_join(F.transform(sigs, lambda s: F.lower(F.hex(s))), " ")


def likeness(a: Column, b: Column) -> Column:
    """Jaccard similarity of two signature sets; two empty ones are alike."""
    both = F.size(F.array_intersect(a, b))
    return F.when((F.size(a) == 0) & (F.size(b) == 0), F.lit(1.0)).otherwise(both / F.greatest(F.size(a) + F.size(b) - both, F.lit(1)))


def with_next(docs: DataFrame, columns: list[str]) -> DataFrame:
    """docs with next_<column> of the row that follows in the order of (doc_id, text hash); the last is followed by the first.

    Rows without doc_id come first. The order is cut into ranges of about equal counts, from
    a light pass over the ids; the first row of each range is also sent to the range before.
    """
    spark = docs.sparkSession
    ranges = min(MOST_RANGES, int(spark.conf.get("spark.sql.shuffle.partitions")))
    h1, _ = text_key(F.col("text"))
    docs = docs.withColumn("h1", h1)
    key = F.struct(F.col("doc_id").isNotNull().alias("named"), F.coalesce(F.col("doc_id"), F.lit(0)).alias("id"), F.col("h1").alias("h"))
    light = docs.select(key.alias("k"))
    edges = [r.k for r in light.repartitionByRange(ranges, "k").groupBy(F.spark_partition_id().alias("p")).agg(F.min("k").alias("k")).orderBy("k").collect()]
    if not edges:
        return docs.drop("h1").select("*", *(F.col(c).alias(f"next_{c}") for c in columns))
    kind = "struct<named:boolean,id:bigint,h:bigint>"
    edge = lambda e: F.struct(F.lit(e.named).alias("named"), F.lit(e.id).cast("long").alias("id"), F.lit(e.h).cast("long").alias("h")).cast(kind)
    cuts = F.array(*(edge(e) for e in edges))
    place = F.size(F.filter(cuts, lambda e: e <= F.col("k"))) - 1
    first = F.array_contains(cuts, F.col("k"))
    rows = docs.withColumn("k", key).withColumn("range", place)
    rows = rows.withColumn("to", F.explode(F.when(first, F.array(F.struct("range", F.lit(False).alias("guest")), F.struct(F.pmod(F.col("range") - 1, F.lit(len(edges))).alias("range"), F.lit(True).alias("guest")))).otherwise(F.array(F.struct("range", F.lit(False).alias("guest"))))))
    rows = rows.drop("range").select("*", "to.range", "to.guest").drop("to")
    w = Window.partitionBy("range").orderBy("guest", "k")
    return rows.select("*", *(F.lead(c).over(w).alias(f"next_{c}") for c in columns)).where(~F.col("guest")).drop("guest", "range", "k", "h1")


def fingerprint_edits(docs: DataFrame) -> DataFrame:
    """One row per row of docs(doc_id, text): its fingerprint, that of its edited text, and their likeness.

    The edited text has its last floor(n / 2) code points replaced by the first as many (or
    all) of the next document's. Null texts count as empty. Rows with one doc_id follow each
    other in the order of their texts' hashes, and each gets a row. Other columns are ignored.
    """
    docs = docs.select(F.col("doc_id").cast("long").alias("doc_id"), F.coalesce(F.col("text").cast("string"), F.lit("")).alias("text"))
    rows = with_next(docs.withColumn("sigs", signatures(F.col("text"))), ["text", "sigs"])
    n = F.length("text")
    half = F.floor(n / 2).cast("int")
    rows = rows.select("doc_id", n.cast("long").alias("n_chars"), "sigs", "next_sigs", F.concat(F.substring(F.col("text"), F.lit(1), n - half), F.substring(F.col("next_text"), F.lit(1), half)).alias("edited"))
    rows = rows.select("doc_id", "n_chars", F.sha2("edited", 256).alias("edited_sha256"), "sigs", "next_sigs", signatures(F.col("edited")).alias("edited_sigs"))
    return rows.select("doc_id", "n_chars", "edited_sha256", as_text(F.col("sigs")).alias("fingerprint"), as_text(F.col("edited_sigs")).alias("edited_fingerprint"), likeness(F.col("sigs"), F.col("edited_sigs")).alias("near_edited"), likeness(F.col("sigs"), F.col("next_sigs")).alias("near_next"))


def spot_pairs(docs: DataFrame, least: float = 0.75) -> tuple[DataFrame, DataFrame]:
    """(members, pairs): the class of each document, and the pairs of classes whose sets are alike by at least `least`.

    members has (doc_id, class, n_signatures); documents with equal sets form a class, named
    by the smallest doc_id. pairs has (a, b, likeness) with a < b. Sets fall into ranges of
    length by powers of 1 / least, so partners are in the same range or the next one; a set
    enters with its rarest signatures, as many as it may lack and one more. Documents without
    signatures are in no pair. Lossless for every pair of classes.
    """
    base = docs.select(F.col("doc_id").cast("long").alias("doc_id"), signatures(F.col("text").cast("string")).alias("sigs"))
    base = base.withColumn("set", F.sha2(F.to_json("sigs"), 256))
    members = materialize(base.select("doc_id", "set", F.size("sigs").cast("long").alias("n_signatures")), "spot_rows")
    names = members.groupBy("set").agg(F.min("doc_id").alias("class"))
    sets = materialize(base.where(F.size("sigs") > 0).dropDuplicates(["set"]).join(names, "set").select("class", "sigs"), "spot_sets")
    one = sets.select("class", F.size("sigs").alias("n"), F.explode("sigs").alias("sig"))
    rare = one.groupBy("sig").agg(F.count(F.lit(1)).alias("df"))
    ranked = one.join(rare, "sig").withColumn("at", F.row_number().over(Window.partitionBy("class").orderBy("df", "sig")))
    prefix = ranked.where("df > 1").where(F.col("at") <= F.col("n") - F.ceil(F.col("n") * least - 1e-9) + 1)
    step = math.log(1 / least)
    bucket = F.floor(F.log(F.col("n").cast("double")) / step).cast("int")
    own = prefix.withColumn("range", bucket)
    entries = own.withColumn("role", F.lit("own")).unionAll(own.withColumn("range", F.col("range") + 1).withColumn("role", F.lit("guest")))
    x, y = entries.where("role = 'own'").alias("x"), entries.alias("y")
    met = x.join(y, (F.col("x.range") == F.col("y.range")) & (F.col("x.sig") == F.col("y.sig")) & (F.col("x.class") != F.col("y.class")) & (F.col("x.n") >= F.col("y.n")) & (F.col("y.n") >= F.col("x.n") * least - 1e-9))
    pairs = met.select(F.least("x.class", "y.class").alias("a"), F.greatest("x.class", "y.class").alias("b")).distinct()
    alike = pairs.join(sets.select(F.col("class").alias("a"), F.col("sigs").alias("sa")), "a").join(sets.select(F.col("class").alias("b"), F.col("sigs").alias("sb")), "b").select("a", "b", likeness(F.col("sa"), F.col("sb")).alias("likeness")).where(F.col("likeness") >= least - 1e-12)
    return members.join(names, "set").select("doc_id", "class", "n_signatures"), alike
