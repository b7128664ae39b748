"""The training-data pipeline over ``documents``: quality rules, line dedup, near-dedup, mixing and packing.

Every stage works on all rows that its predecessor kept, and all but the last return the columns of documents.
"""

from __future__ import annotations

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F
from pyspark.sql.window import Window

from poslp.llm.common import materialise, table
from poslp.llm.line_dedup import line_dedup
from poslp.llm.mixing import mix
from poslp.llm.near_copies import near_components
from poslp.llm.packing import pack, pieces
from poslp.llm.quality_rules import judge, measure

#: No source is passed over more than this many times in the mixture.
MAX_REPEATS = 1.5


def quality(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """Documents that the quality rules reject go; the rest pass untouched."""
    return judge(measure(docs, docs.columns)).where("kept").select("_row.*")


def lines(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """Lines that many documents share go, but from the last document; n_chars follows the text."""
    out = line_dedup(docs)
    if "n_chars" in docs.columns:
        out = out.withColumn("n_chars", F.length("text").cast("long"))
    return out.select(*docs.columns)


def near_dedup(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """Of each component of near copies (five-word shingles, Jaccard 0.8 or more) the document with the least doc_id stays,
    once. Rows without a doc_id stay. SimHash links are confirmed on the sets, which also find what four bits can't."""
    first = materialise(near_components(docs).select(F.col("component_id").alias("_first")).distinct(), "stays")
    both = docs.join(first, docs["doc_id"] == first["_first"], "left").where(F.col("_first").isNotNull() | F.col("doc_id").isNull())
    lot = F.xxhash64(*[F.col(f"`{c}`") for c in docs.columns])  # rows of one doc_id that differ: any, but always the same
    once = both.withColumn("_lot", lot)
    once = once.withColumn("_k", F.row_number().over(Window.partitionBy("_first", F.when(F.col("_first").isNull(), F.col("_lot"))).orderBy("_lot")))
    return once.where((F.col("_k") == 1) | F.col("_first").isNull()).select(*docs.columns)


def mixing(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """Every document at least once; documents of smaller sources again, as their weight asks."""
    return mix(docs, max_repeats=MAX_REPEATS).select(*docs.columns)


def packing(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    return pack(materialise(pieces(docs), "pieces")).select("doc_id", "start", "length", "ids_crc32", "doc_tokens", "sequence_id", "offset")


STAGES = [("quality rules", quality), ("line dedup", lines), ("simhash near-dedup", near_dedup), ("mixing", mixing), ("packing", packing)]

#: Near copies, divergence and packing have no SQL form here; tests/llm holds the stages against brute force.
ORACLE_SQL = None


def run(spark: SparkSession, sf_dir: str) -> DataFrame:
    docs = table(spark, sf_dir, "documents")
    for k, (_, stage) in enumerate(STAGES):
        docs = stage(spark, docs, sf_dir)
        if k + 1 < len(STAGES):
            docs = materialise(docs, f"stage-{k}")
    return docs
