"""Mixing sources to target weights by temperature.

Source weights are their token shares raised to an exponent and normalised. The exponent is bisected, as far as the
target asks: until the weights reach a target entropy, or until no source is repeated more than a limit. Weights
become token budgets, whole passes over a source and one partial pass. A pass is a permutation of the source's
blocks, and of the documents inside a block; the partial pass takes whole blocks while they fit, and documents of
the block where the budget ends.

Blocks come from hashing doc_id, some hundreds of documents each (the square root of a source's rows if that is more), so a source with a third
of all rows is many groups. All steps are DataFrame functions; the driver sees one row of scalars per bisection pass
(64 exponents are tried in each), never a row per source.

Defined results: null or empty text has no tokens and goes with every pass of its source; a null source is a source
of its own; repeated rows stay apart; an empty table gives an empty table; other columns pass through untouched.
"""

from __future__ import annotations

from pyspark.sql import Column, DataFrame, SparkSession
from pyspark.sql import functions as F
from pyspark.sql.window import Window

from poslp.llm.common import materialise, table, words

BLOCK_ROWS = 500
LANES = 64


def word_tokens(text: Column) -> Column:
    return F.size(words(text)).cast("long")


def find_exponent(shares: DataFrame, target_entropy: float | None = None, max_repeats: float | None = None, volume: float | None = None, passes: int = 6) -> float:
    """The largest exponent in [0, 1] whose weights have at least the target entropy (in nats, at most that of equal
    weights), made larger as far as needed for no source to be passed over more than max_repeats times; with no target
    entropy, the least exponent that the repeats allow. shares: (share), one row a source, from a table. volume: the
    budget over all tokens; None for the least that passes over every source once."""
    lo, hi = 0.0, 1.0

    def lanes(a: float, b: float) -> list[float]:
        return [a + (b - a) * k / (LANES - 1) for k in range(LANES)]

    def evaluate(tried: list[float]) -> list[tuple[float, float]]:
        z = shares.agg(*[F.sum(F.pow("share", F.lit(t))).alias(f"z{k}") for k, t in enumerate(tried)]).first()
        if z[0] is None:
            return [(0.0, 0.0)] * len(tried)
        cols = []
        for k, t in enumerate(tried):
            w = F.pow("share", F.lit(t)) / F.lit(float(z[k]))
            cols += [F.sum(-w * F.log(w)), F.max(w / F.col("share")), F.max(F.col("share") / w)]
        r = shares.agg(*cols).first()
        return [(r[3 * k], r[3 * k + 1] * (r[3 * k + 2] if volume is None else volume)) for k in range(len(tried))]

    def last_true(test, a: float, b: float) -> float:
        """The end of the run of exponents from a that pass; a itself is taken to pass."""
        for _ in range(passes):
            tried = lanes(a, b)
            ok = [test(*v) for v in evaluate(tried)]
            k = next((i for i, x in enumerate(ok) if not x and i), LANES)
            if k == LANES:
                return b
            a, b = tried[k - 1], tried[k]
        return a

    def first_true(test, a: float, b: float) -> float:
        for _ in range(passes):
            tried = lanes(a, b)
            ok = [test(*v) for v in evaluate(tried)]
            k = next((i for i, x in enumerate(ok) if x), LANES - 1)
            if k == 0:
                return a
            a, b = tried[k - 1], tried[k]
        return b

    out = last_true(lambda entropy, _: entropy >= target_entropy - 1e-12, lo, hi) if target_entropy is not None else (0.0 if max_repeats is not None else 1.0)
    if max_repeats is not None:
        out = max(out, first_true(lambda _, most: most <= max_repeats + 1e-12, out, hi))
    return out


def mix(docs: DataFrame, target_entropy: float | None = None, max_repeats: float | None = 2.0, budget: int | None = None, seed: int = 17, id_col: str = "doc_id", source_col: str = "source", text_col: str = "text", name: str = "mix") -> DataFrame:
    """docs' rows, each as often as its source's budget takes it, with _tokens, _epoch, _block, _block_place and _place:
    ordered by (_epoch, _block_place, _place), a source's rows follow its block permutations. budget: tokens in all; by
    default the least with which every source is passed over at least once, so that no row goes."""
    keyed = docs.select(F.col(id_col).alias("_id"), F.struct(F.col(source_col)).alias("_source"), word_tokens(F.col(text_col)).alias("_tokens"))
    keyed = materialise(keyed, f"{name}-tokens")
    sources = keyed.groupBy("_source").agg(F.sum("_tokens").alias("_have"), F.count(F.lit(1)).alias("_rows"))
    sources = materialise(sources, f"{name}-sources")
    total = sources.agg(F.sum("_have")).first()[0] or 0
    shares = sources.where(F.col("_have") > 0).select((F.col("_have") / F.lit(max(1, total))).alias("share"))
    exponent = find_exponent(shares, target_entropy, max_repeats, None if budget is None else budget / max(1, total))
    z, thin = shares.agg(F.sum(F.pow("share", F.lit(exponent))), F.max(F.pow("share", F.lit(1 - exponent)))).first()
    z = z or 1.0
    want = float(budget if budget is not None else total * (thin or 1.0) * z)
    weight = F.when(F.col("_have") > 0, F.pow(F.col("_have") / F.lit(max(1, total)), F.lit(exponent)) / F.lit(z)).otherwise(0.0)
    plan = sources.withColumn("_budget", F.floor(weight * F.lit(want * (1 + 1e-9)) + F.lit(1e-6)).cast("long"))
    plan = plan.withColumns({
        "_whole": F.when(F.col("_have") > 0, F.floor(F.col("_budget") / F.col("_have"))).otherwise(1).cast("long"),
        "_blocks": F.greatest(F.lit(1), F.floor(F.col("_rows") / F.greatest(F.lit(BLOCK_ROWS), F.sqrt("_rows")))).cast("long"),
    })
    plan = materialise(plan.withColumn("_part", F.when(F.col("_have") > 0, F.col("_budget") - F.col("_whole") * F.col("_have")).otherwise(0)), f"{name}-plan")
    # where each block stands in the partial pass
    in_blocks = _with_blocks(keyed, plan, seed)
    held = in_blocks.groupBy("_source", "_block").agg(F.sum("_tokens").alias("_in"), F.first("_whole").alias("_whole"), F.first("_part").alias("_part"))
    order = Window.partitionBy("_source").orderBy(F.xxhash64(F.lit(seed), F.col("_whole"), "_block"), "_block")
    before = F.coalesce(F.sum("_in").over(order.rowsBetween(Window.unboundedPreceding, -1)), F.lit(0))
    held = held.withColumn("_left", F.col("_part") - before).select("_source", "_block", "_in", "_left")
    held = materialise(held, f"{name}-blocks")
    rows = _with_blocks(docs.withColumns({"_id": F.col(id_col), "_source": F.struct(F.col(source_col)), "_tokens": word_tokens(F.col(text_col))}), plan, seed)
    rows = rows.join(held, ["_source", "_block"])
    shuffled = F.xxhash64(F.lit(seed), F.col("_whole"), F.col("_id"))
    used = F.coalesce(F.sum("_tokens").over(Window.partitionBy("_source", "_block").orderBy(shuffled, "_id").rowsBetween(Window.unboundedPreceding, 0)), F.lit(0))
    rows = rows.withColumn("_extra", (F.col("_left") > 0) & ((F.col("_in") <= F.col("_left")) | (used <= F.col("_left"))))
    times = F.col("_whole") + F.when(F.col("_extra") & (F.col("_part") > 0), 1).otherwise(0)
    rows = rows.withColumn("_epoch", F.explode(F.when(times > 0, F.sequence(F.lit(0).cast("long"), times - 1)).otherwise(F.array().cast("array<bigint>"))))
    rows = rows.withColumns({"_place": F.xxhash64(F.lit(seed), "_epoch", "_id"), "_block_place": F.xxhash64(F.lit(seed), "_epoch", "_source", "_block")})
    return rows.select(*[F.col(f"`{c}`") for c in docs.columns], "_tokens", "_epoch", "_block", "_block_place", "_place")


def _with_blocks(rows: DataFrame, plan: DataFrame, seed: int) -> DataFrame:
    p = plan.select(F.col("_source").alias("_s1"), "_blocks", "_whole", "_part")
    out = rows.join(p, F.col("_source") == F.col("_s1")).drop("_s1")
    return out.withColumn("_block", F.pmod(F.xxhash64(F.lit(seed), "_id"), F.col("_blocks")))


def op5_mixing(spark: SparkSession, sf_dir: str) -> DataFrame:
    """The mixture that passes over every source at least once and is as even as two passes at most allow."""
    out = mix(table(spark, sf_dir, "documents").select("doc_id", "source", "text"))
    return out.select("doc_id", "source", F.col("_tokens").alias("n_tokens"), F.col("_epoch").alias("epoch"), F.col("_block").alias("block"), F.col("_block_place").alias("block_place"), F.col("_place").alias("place"))
