"""A training corpus from ``documents``: five stages, each written as Parquet and read again as the next one's documents."""

from __future__ import annotations

from pyspark.sql import Column, DataFrame, SparkSession, Window
from pyspark.sql import functions as F

from kinetic.llm.common import table, written
from kinetic.llm.exact_dedup import exact_dedup, normalised
from kinetic.llm.mixing import in_mixed_order
from kinetic.llm.ngram_join import one_of_each
from kinetic.llm.packing import pack_mixed
from kinetic.llm.quality import good_rows


def quality(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """Documents that the neighbours' vote does not reject."""
    return good_rows(docs, table(spark, sf_dir, "labels"))


def _key() -> Column:
    """The id, with a stand-in for null, so that rows meet in one plain join."""
    return F.coalesce(F.col("doc_id"), F.lit(-(2**63)))


def exact(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """The document that stays of each group of equal texts; the longest row of it where a table repeats its id.

    Ids may be null or name several texts, so a decision belongs to an id and a digest. The rows kept of one digest have one id.
    """
    own = F.struct(_key().alias("k"), F.col("doc_id").isNull().alias("none"))
    kept = exact_dedup(docs).where("kept").select(own.alias("own"), F.unhex("text_sha256").alias("digest")).distinct()
    text = F.col("text")
    rows = docs.select(F.struct(*[F.col(f"`{c}`") for c in docs.columns]).alias("row"), own.alias("own"), F.unhex(F.sha2(normalised(text), 256)).alias("digest"), F.char_length(text).alias("size"), F.xxhash64(text).alias("tie"))
    first = F.row_number().over(Window.partitionBy("own", "digest").orderBy(F.col("size").desc_nulls_last(), "tie"))  # a limit of one row goes before the shuffle
    return rows.withColumn("r", first).where("r = 1").join(kept, ["own", "digest"], "left_semi").select(*[F.col(f"row.`{c}`").alias(c) for c in docs.columns])


def near(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """Of each group that hangs together by n-gram links the document with the least id (null ids last); documents without words stay."""
    return one_of_each(docs)


def mixing(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """Every document, in files in the order of the mix: any beginning of them has the sources at their target weights."""
    return in_mixed_order(docs)


def packing(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """Every piece of every document with its sequence and place; sequences are numbered, and filled, in the order of the mix."""
    return pack_mixed(docs)


STAGES = [("quality", quality), ("exact_dedup", exact), ("near_duplicates", near), ("mixing", mixing), ("packing", packing)]

#: The neighbours' vote cannot be said in SQL; tests hold the stages against brute force.
ORACLE_SQL = None


def run(spark: SparkSession, sf_dir: str) -> DataFrame:
    """STAGES over ``documents``; what a stage returns is written to the shared folder and read again."""
    docs = table(spark, sf_dir, "documents")
    for name, stage in STAGES[:-1]:
        docs = written(stage(spark, docs, sf_dir), name)
    return STAGES[-1][1](spark, docs, sf_dir)
