"""Chat formatting after collapsing cumulative snapshots.

A log that saves a conversation after every turn holds each prefix of it as a conversation of its own. Every turn
gets the hash of its conversation up to it: the XOR of 128-bit hashes of (place, role, text), so prefixes extend in
one window. Conversations that are equal as a whole leave their least conv_id; an anti-join then drops those whose
whole hash and length are a proper prefix of a longer one. What is left is rendered turn by turn.

Prefix hashes are made distinct with map-side combine before they are shuffled, so an opening that a third of all
conversations share is one row a task. One conversation is one rendered row and must fit a task; copies need not.

Defined results: turns are ordered by (turn, role, text), nulls first; repeated rows are repeated turns; a null
conv_id is a conversation of its own; a null role is rendered as "unknown", a null text as empty (but neither equals
the non-null value in the comparison); an empty table gives an empty table; only the four columns are read.
"""

from __future__ import annotations

from pyspark.sql import Column, DataFrame, SparkSession
from pyspark.sql import functions as F
from pyspark.sql.window import Window

from poslp.llm.common import materialise, table

#: The marks of the template.
START, END = "<|im_start|>", "<|im_end|>"


def render(role: Column, text: Column) -> Column:
    """One turn. A mark inside a text or role is broken by a space and a line end in a role becomes one, so neither can
    open or close a turn."""
    safe = lambda x: F.replace(F.replace(x, F.lit(START), F.lit("<| im_start|>")), F.lit(END), F.lit("<| im_end|>"))
    named = F.translate(safe(F.coalesce(role, F.lit("unknown"))), "\n", " ")
    return F.concat(F.lit(START), named, F.lit("\n"), safe(F.coalesce(text, F.lit(""))), F.lit(END + "\n"))


def prefix_hashes(turns: DataFrame) -> DataFrame:
    """turns with _key (the conversation), _i (from 1), _n (its turns) and the prefix hash _a, _b."""
    turns = turns.select(F.struct("conv_id").alias("_key"), "turn", "role", "text")
    ordered = Window.partitionBy("_key").orderBy("turn", "role", "text")
    out = turns.withColumn("_i", F.row_number().over(ordered))
    # nulls must count, and xxhash64 skips them
    shape = F.concat(F.col("role").isNull().cast("string"), F.col("text").isNull().cast("string"))
    up_to = Window.partitionBy("_key").orderBy("_i").rowsBetween(Window.unboundedPreceding, 0)
    every = Window.partitionBy("_key")
    hashes = [F.xxhash64(F.lit(seed), "_i", shape, F.coalesce("role", F.lit("")), F.coalesce("text", F.lit(""))) for seed in (1, 2)]
    return out.withColumns({"_n": F.count(F.lit(1)).over(every), "_a": F.bit_xor(hashes[0]).over(up_to), "_b": F.bit_xor(hashes[1]).over(up_to)})


def maximal(hashed: DataFrame) -> DataFrame:
    """(_key): the conversations that no other holds as a proper prefix, one of each group of equal ones."""
    whole = hashed.where(F.col("_i") == F.col("_n")).groupBy("_a", "_b", "_n").agg(F.min("_key").alias("_key"))
    begun = hashed.where(F.col("_i") < F.col("_n")).select("_a", "_b", F.col("_i").cast("long").alias("_n")).distinct()
    return whole.join(begun, ["_a", "_b", "_n"], "left_anti").select("_key")


def chat_format(turns: DataFrame) -> DataFrame:
    """(conv_id, n_turns, rendered) of the maximal conversations."""
    hashed = materialise(prefix_hashes(turns).select("_key", "_i", "_n", "_a", "_b", render(F.col("role"), F.col("text")).alias("_turn")), "turn-hashes")
    kept = materialise(maximal(hashed), "maximal")
    rows = hashed.select("_key", "_i", "_turn").join(kept, "_key")
    out = rows.groupBy("_key").agg(F.sort_array(F.collect_list(F.struct("_i", "_turn"))).alias("_turns"))
    return out.select(F.col("_key.conv_id").alias("conv_id"), F.size("_turns").cast("long").alias("n_turns"), F.array_join(F.transform("_turns", lambda x: x["_turn"]), "").alias("rendered"))


def op8_chat_format(spark: SparkSession, sf_dir: str) -> DataFrame:
    return chat_format(table(spark, sf_dir, "conversations"))


ORACLE = """
WITH placed AS (
  SELECT conv_id, role, text, row_number() OVER (PARTITION BY conv_id ORDER BY turn NULLS FIRST, role NULLS FIRST, text NULLS FIRST) AS i,
         count(*) OVER (PARTITION BY conv_id) AS n
  FROM conversations),
prefixed AS (
  SELECT *, string_agg(coalesce('r' || role, 'n') || chr(1) || coalesce('t' || text, 'n') || chr(2), '') OVER (PARTITION BY conv_id ORDER BY i) AS upto
  FROM placed),
whole AS (SELECT upto, n, min(conv_id) AS conv_id FROM prefixed WHERE i = n GROUP BY upto, n),
kept AS (SELECT conv_id FROM whole w WHERE NOT EXISTS (SELECT 1 FROM prefixed p WHERE p.i < p.n AND p.i = w.n AND p.upto = w.upto))
SELECT p.conv_id, count(*)::BIGINT AS n_turns,
       string_agg('<|im_start|>' || translate(replace(replace(coalesce(role, 'unknown'), '<|im_start|>', '<| im_start|>'), '<|im_end|>', '<| im_end|>'), chr(10), ' ') || chr(10)
         || replace(replace(coalesce(text, ''), '<|im_start|>', '<| im_start|>'), '<|im_end|>', '<| im_end|>') || '<|im_end|>' || chr(10), '' ORDER BY i) AS rendered
FROM placed p JOIN kept k ON p.conv_id = k.conv_id GROUP BY p.conv_id
"""
