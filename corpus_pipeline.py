"""The corpus pipeline: language, near copies, repeated passages, benchmark passages, packing.

Each stage takes (spark, docs, sf_dir), works on all its predecessor kept, and is written
and read again before the next. All but the last return the columns of documents.
"""

from __future__ import annotations

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from codematch.functions.arrays import text_key
from codematch.llm import jaccard_join, language, packing, repeats, winnowing
from codematch.llm.joins import left_join
from codematch.sources.io import discard, materialize, read_table

COLUMNS = ["doc_id", "text", "lang", "source", "n_chars"]


def keep_languages(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """Documents with a recognizable language; lang and source are evidence and stay as they are."""
    return language.identify(docs, declared=F.col("lang"), host=F.col("source")).where("lid_accepted").select(*COLUMNS)


def keep_one_of_near_copies(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """Of each group of near copies, the row with the smallest doc_id (and text hashes); rows without words or doc_id stay.

    A doc_id that stands on rows with different texts goes only with the texts that have copies.
    """
    found = jaccard_join.jaccard_components(docs.select("doc_id", "text"), with_keys=True)
    found = materialize(found.where("part IS NOT NULL AND doc_id IS NOT NULL"), "components")
    row = F.struct("doc_id", "h1", "h2")
    many = found.groupBy(F.col("part").alias("group")).agg(F.min(row).alias("first"), F.count(F.lit(1)).alias("rows")).where("rows > 1")
    many = materialize(many, "groups")
    of_group = left_join(found, many, {"part": "group"}, size="rows", found="first")
    gone = materialize(of_group.where(row != F.col("first")).select("doc_id", "h1", "h2").distinct(), "gone")
    h1, h2 = text_key(F.col("text"))
    keyed = docs.withColumns({"h1": h1, "h2": h2})
    few = F.broadcast(gone) if gone.count() <= winnowing.BROADCAST_ROWS else gone
    kept = keyed.join(few, ["doc_id", "h1", "h2"], "left_anti")
    if of_group.where(row == F.col("first")).groupBy("doc_id", "h1", "h2").count().where("count > 1").limit(1).count():
        named = kept.where("doc_id IS NOT NULL AND text IS NOT NULL").dropDuplicates(["doc_id", "h1", "h2"])
        kept = named.unionByName(kept.where("doc_id IS NULL OR text IS NULL"))
    return kept.select(*COLUMNS)


def cut_repeated_passages(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """Texts without the bytes of repeated passages; a character that a cut splits goes. Documents with nothing left go."""
    cut = repeats.cut_repeats(docs, with_text=True, carry=("lang", "source", "n_chars"))
    whole = F.col("n_removed") == 0
    n_chars = F.when(whole, F.col("n_chars")).otherwise(F.length("kept").cast("long"))
    left = cut.where(whole | (F.trim("kept") != "")).withColumn("n_chars", n_chars)
    return left.select("doc_id", F.col("kept").alias("text"), "lang", "source", "n_chars")


def drop_contaminated(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """Documents without any window of a benchmark item."""
    return winnowing.clean_documents(docs, read_table(spark, sf_dir, "benchmark").select("item_id", "text"))


def pack_bins(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """One row per piece of a document: the bin that holds it."""
    return packing.pack(docs)


STAGES = [
    ("language ID", keep_languages),
    ("n-gram Jaccard join", keep_one_of_near_copies),
    ("suffix-array dedup", cut_repeated_passages),
    ("benchmark decontamination", drop_contaminated),
    ("best-fit packing", pack_bins),
]
#: Language evidence, byte repeats and packing have no SQL form; tests/llm holds them against brute force.
ORACLE_SQL = None


def run(spark: SparkSession, sf_dir: str) -> DataFrame:
    """All stages over documents."""
    docs = read_table(spark, sf_dir, "documents").select(*COLUMNS)
    for name, stage in STAGES[:-1]:
        kept = materialize(stage(spark, docs, sf_dir), "stage-" + name.replace(" ", "-"))
        discard(docs)
        docs = kept
    return STAGES[-1][1](spark, docs, sf_dir)
