"""Removal of lines that many documents share.

Lines of at least ``min_chars`` code points (after stripping white space and lower-casing A-Z) are hashed to
128 bits and exploded once per row; one aggregate with map-side combine counts the rows of each hash, and among the
few hashes that enough rows hold, distinct doc_ids are counted and the largest found. Hashes over the threshold are
joined back to the (doc_id, hash) rows, never to the text; the text moves once, to meet its own list of dropped hashes,
and is reassembled by position in the row.

Defined results: null or empty text is one empty line; rows that share a doc_id are one document in the count, each is
returned, and every row under the largest doc_id keeps the line; rows with a null doc_id count towards nothing and keep
all lines; an empty table gives an empty table; only the id and text columns are read, the others pass through untouched.
"""

from __future__ import annotations

from pyspark.sql import Column, DataFrame, SparkSession
from pyspark.sql import functions as F

from poslp.llm.common import LOWER, UPPER, WHITE, ascii_lower, lines, materialise, table


def _hash(line: Column, min_chars: int) -> Column:
    key = ascii_lower(F.btrim(line, F.lit(WHITE)))
    return F.when(F.length(key) >= min_chars, F.struct(F.xxhash64(key).alias("a"), F.xxhash64(F.lit(1), key).alias("b")))


def shared_lines(docs: DataFrame, min_docs: int, min_chars: int, id_col: str, text_col: str) -> DataFrame:
    """(_id, _a, _b): the hashes of the lines that each document loses."""
    found = F.filter(F.transform(lines(F.col(text_col)), lambda x: _hash(x, min_chars)), lambda h: h.isNotNull())
    held = docs.select(F.col(id_col).alias("_id"), F.explode(F.array_distinct(found)).alias("_h"))
    held = materialise(held.select("_id", F.col("_h.a").alias("_a"), F.col("_h.b").alias("_b")), "line-hashes")
    often = held.groupBy("_a", "_b").agg(F.count(F.lit(1)).alias("_n")).where(F.col("_n") >= min_docs)
    hit = materialise(held.join(materialise(often.select("_a", "_b"), "frequent-lines"), ["_a", "_b"]), "frequent-line-rows")
    last = hit.groupBy("_a", "_b").agg(F.count_distinct("_id").alias("_n"), F.max("_id").alias("_last")).where(F.col("_n") >= min_docs)
    last = materialise(last.select("_a", "_b", "_last"), "shared-lines")
    return hit.join(last, ["_a", "_b"]).where(F.col("_id") < F.col("_last")).select("_id", "_a", "_b")


def line_dedup(docs: DataFrame, min_docs: int = 5, min_chars: int = 40, id_col: str = "doc_id", text_col: str = "text") -> DataFrame:
    """The rows of docs with ``text`` reassembled, and _n_lines and _n_dropped."""
    lost = shared_lines(docs, min_docs, min_chars, id_col, text_col).groupBy("_id").agg(F.collect_set(F.struct(F.col("_a").alias("a"), F.col("_b").alias("b"))).alias("_lost"))
    both = docs.join(lost, docs[id_col] == lost["_id"], "left").drop("_id")
    kept = F.filter(lines(F.col(text_col)), lambda x: F.coalesce(~F.array_contains(F.col("_lost"), _hash(x, min_chars)), F.lit(True)))
    out = both.withColumn("_lines", lines(F.col(text_col))).withColumn("_kept", F.when(F.col("_lost").isNull(), F.col("_lines")).otherwise(kept))
    out = out.withColumns({"_n_lines": F.size("_lines").cast("long"), "_n_dropped": (F.size("_lines") - F.size("_kept")).cast("long"), text_col: F.array_join("_kept", "\n")})
    return out.drop("_lost", "_lines", "_kept")


def op4_line_dedup(spark: SparkSession, sf_dir: str) -> DataFrame:
    out = line_dedup(table(spark, sf_dir, "documents").select("doc_id", "text"))
    return out.select("doc_id", F.col("_n_lines").alias("n_lines"), F.col("_n_dropped").alias("n_dropped"), F.sha2("text", 256).alias("kept_sha256"))


ORACLE = f"""
WITH split AS (
  SELECT doc_id, unnest(string_split(coalesce(text, ''), chr(10))) AS line,
         generate_subscripts(string_split(coalesce(text, ''), chr(10)), 1) AS pos
  FROM documents),
keyed AS (
  SELECT doc_id, pos, line,
         translate(trim(line, chr(32) || chr(9) || chr(10) || chr(11) || chr(12) || chr(13)), '{UPPER}', '{LOWER}') AS key
  FROM split),
often AS (
  SELECT key, max(doc_id) AS last_doc FROM keyed WHERE length(key) >= 40
  GROUP BY key HAVING count(DISTINCT doc_id) >= 5),
marked AS (
  SELECT k.*, (o.key IS NOT NULL AND k.doc_id < o.last_doc) AS dropped FROM keyed k LEFT JOIN often o ON k.key = o.key)
SELECT doc_id, count(*)::BIGINT AS n_lines, count(*) FILTER (WHERE dropped)::BIGINT AS n_dropped,
       sha256(coalesce(string_agg(line, chr(10) ORDER BY pos) FILTER (WHERE NOT dropped), '')) AS kept_sha256
FROM marked GROUP BY doc_id
"""
