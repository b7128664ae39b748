"""Quality rules: base counts, then divergence of a document from its language's usual text.

Every whole text is measured inside its own row, with built-in functions alone and no shuffle of text. A first
scan counts words per language with map-side combine; each language's most frequent words and its character
classes, over all documents, are its reference. The class sums are taken twice: all documents count in both, in the
second by a weight that falls with their distance from the first. A document is rejected when the Jensen-Shannon distance
(base 2, square root of the divergence) between its own histogram and the reference exceeds a threshold, and the document
is long enough for the histogram to mean something: the class histogram counts from ``min_chars`` characters, the
common-word histogram from ``min_words`` words.

References: every language with ``MIN_REFERENCE`` words or more has its own; shorter ones, which a few documents could
be the whole of, are measured against the reference over all documents. References are joined by key; Spark broadcasts
them only under its size threshold, which thousands of languages do not reach.

Defined results: null or empty text has no words and fails the base rule; a null language is the empty one; repeated
rows are separate rows; an empty table gives an empty table; other columns take no part.
"""

from __future__ import annotations

from pyspark.sql import Column, DataFrame, SparkSession
from pyspark.sql import functions as F
from pyspark.sql.window import Window

from poslp.llm.common import WHITE, WORD, let, lines, materialise, table

#: Words of a language from which it has a reference of its own.
MIN_REFERENCE = 2_000
COMMON = 24
#: Parts of a language's words that are ranked apart before its most frequent ones are.
SALTS = 32
#: The characters counted as symbols by the contract, and the stops of the class histogram.
SYMBOLS = "#*$%&|<>"
STOPS = ".,;:!?'\"()-"
#: lower-case and upper-case letters, digits, white space, stops, other ASCII, all else
CLASSES = 7
#: Repeated windows up to which their places are looked up one by one, beyond which all windows are sorted.
FEW = 48
COUNTS = ("n_words", "word_chars", "n_symbols", "n_dup_lines", "n_repeat_words")
#: Distance from the first class reference at which a document counts half in the second, final one.
HALF = 0.2
#: The weight of a document at distance zero; weights are whole numbers, so that sums do not depend on their order.
FULL = 1024
#: Thresholds, set on the labelled documents so that clean ones stay far below them.
MAX_CLASS_DISTANCE = 0.3
MAX_WORD_DISTANCE = 0.42
MIN_CHARS = 200
MIN_WORDS = 50


def _without(text: str, pattern: str) -> Column:
    return F.regexp_replace(text, F.lit(pattern), F.lit(""))


def split_words(text: Column) -> Column:
    """The words of common.words, by one split in place of a match for each."""
    bare = F.btrim(F.coalesce(text, F.lit("")), F.lit(WHITE))
    return F.when(bare == "", F.array().cast("array<string>")).otherwise(F.split(bare, "[\\x20\\x09-\\x0D]+", -1))


def _lost(longer: Column | str, shorter: Column | str) -> Column:
    return (F.length(longer) - F.length(shorter)).cast("long")


def _covered(places: Column) -> Column:
    """Words covered by the three-word windows that begin at the places, which are in order."""
    return F.aggregate(F.transform(places, lambda p, k: F.coalesce(F.least(F.lit(3), F.get(places, k + 1) - p), F.lit(3))), F.lit(0), lambda a, x: a + x)


def _places(hashes: Column, twice: Column) -> Column:
    """Where the hashes that occur twice or more stand."""
    some = F.filter(F.transform(hashes, lambda h, k: F.when(F.array_contains(twice, h), k)), lambda x: x.isNotNull())

    def sorted_(pairs: Column) -> Column:
        same = lambda x, k: F.coalesce(F.get(pairs, k)["h"] == x["h"], F.lit(False))
        return F.sort_array(F.transform(F.filter(pairs, lambda x, k: same(x, k - 1) | same(x, k + 1)), lambda x: x["i"]))

    many = let(F.sort_array(F.transform(hashes, lambda h, k: F.struct(h.alias("h"), k.alias("i")))), sorted_)
    return F.when(F.size(twice) == 0, F.array().cast("array<int>")).when(F.size(twice) <= FEW, some).otherwise(many)


def with_counts(docs: DataFrame, text_col: str = "text") -> DataFrame:
    """Adds the base counts, _chars, _classes and _words. Each step is a projection of its own, so that the sorts of
    plain arrays run as generated code and nothing is worked out twice."""
    docs = docs.withColumn("_text", F.coalesce(F.col(text_col), F.lit("")))
    docs = docs.withColumns({"_words": split_words(F.col("_text")), "_rest": _without("_text", "[a-z]+"), "_full": F.filter(lines(F.col("_text")), lambda x: x.rlike(WORD))})
    w = F.col("_words")
    windows = F.transform(F.sequence(F.lit(0), F.size(w) - 3), lambda i: F.xxhash64(F.get(w, i), F.get(w, i + 1), F.get(w, i + 2)))
    docs = docs.withColumns({"_hash": F.when(F.size(w) >= 3, windows).otherwise(F.array().cast("array<bigint>")), "_dense": _without("_rest", "[\\x20\\x09-\\x0D]+")})
    docs = docs.withColumn("_ordered", F.sort_array("_hash"))
    docs = docs.withColumn("_twice", F.filter("_ordered", lambda h, k: F.coalesce(F.get(F.col("_ordered"), k - 1) == h, F.lit(False))))
    docs = docs.withColumn("_twice", F.array_distinct("_twice"))
    docs = docs.withColumn("_places", _places(F.col("_hash"), F.col("_twice")))
    dense, rest = F.col("_dense"), F.col("_rest")
    seen = [_lost("_text", rest), _lost(dense, _without("_dense", "[A-Z]+")), _lost(dense, _without("_dense", "[0-9]+")), _lost(rest, dense), _lost(dense, F.translate(dense, STOPS, ""))]
    ascii_ = _lost(dense, _without("_dense", "[\\x00-\\x7F]+"))
    docs = docs.withColumns({
        "n_words": F.size("_words").cast("long"), "word_chars": F.length("_text").cast("long") - _lost(rest, dense), "n_symbols": _lost(dense, F.translate(dense, SYMBOLS, "")),
        "n_dup_lines": (F.size("_full") - F.size(F.array_distinct("_full"))).cast("long"), "n_repeat_words": _covered(F.col("_places")).cast("long"),
        "_chars": F.length("_text").cast("long"), "_classes": F.array(*seen, ascii_ - seen[1] - seen[2] - seen[4], F.length(dense).cast("long") - ascii_),
    })
    return docs.drop("_text", "_rest", "_full", "_hash", "_dense", "_ordered", "_twice", "_places")


def _lang(lang: Column) -> Column:
    return F.coalesce(lang, F.lit(""))


def common_words(docs: DataFrame) -> DataFrame:
    """(_lang, _common, _usual): for each reference, its most frequent words and their counts, then all others' count."""
    counts = docs.select(_lang(F.col("lang")).alias("_lang"), F.explode(split_words(F.col("text"))).alias("_w")).groupBy("_lang", "_w").agg(F.count(F.lit(1)).alias("_n"))
    counts = materialise(counts, "word-counts")
    total = counts.groupBy("_lang").agg(F.sum("_n").alias("_all"))
    named = materialise(total.where(F.col("_all") >= MIN_REFERENCE), "languages")
    order = [F.desc("_n"), F.col("_w")]
    salted = counts.withColumn("_s", F.pmod(F.xxhash64("_w"), F.lit(SALTS)))
    some = salted.withColumn("_r", F.row_number().over(Window.partitionBy("_lang", "_s").orderBy(*order))).where(F.col("_r") <= COMMON)
    top = some.withColumn("_r", F.row_number().over(Window.partitionBy("_lang").orderBy(*order))).where(F.col("_r") <= COMMON)
    top = top.join(named.select("_lang"), "_lang", "left_semi")
    every = counts.groupBy("_w").agg(F.sum("_n").alias("_n")).orderBy(F.desc("_n"), "_w").limit(COMMON)
    ranked = top.select("_lang", "_w", "_n", "_r").unionByName(every.select(F.lit(None).cast("string").alias("_lang"), "_w", "_n", F.row_number().over(Window.partitionBy(F.lit(0)).orderBy(F.desc("_n"), "_w")).alias("_r")))
    totals = named.unionByName(total.agg(F.sum("_all").alias("_all")).select(F.lit(None).cast("string").alias("_lang"), "_all"))
    out = ranked.groupBy("_lang").agg(F.array_sort(F.collect_list(F.struct("_r", "_w", "_n"))).alias("_top")).join(totals.withColumnRenamed("_lang", "_l2"), F.col("_lang").eqNullSafe(F.col("_l2")))
    usual = F.transform("_top", lambda x: x["_n"])
    rest = F.col("_all") - F.aggregate(usual, F.lit(0).cast("long"), lambda a, x: a + x)
    return out.select("_lang", F.transform("_top", lambda x: x["_w"]).alias("_common"), F.array_append(usual, rest).alias("_usual"))


def with_tally(docs: DataFrame) -> DataFrame:
    """Adds _tally: how often each word of the array _common stands in _words, then how many words are none of them."""
    common = F.col("_common")
    longest = F.array_max(F.transform(common, lambda w: F.octet_length(w)))
    short = let(longest, lambda most: F.filter("_words", lambda w: F.octet_length(w) <= most))  # longer words are none of them
    docs = docs.withColumn("_rank", F.filter(F.transform(short, lambda w: F.array_position(common, w).cast("int")), lambda r: r > 0))
    docs = docs.withColumn("_rank", F.sort_array("_rank"))
    rank = F.col("_rank")
    ends = F.transform("_rank", lambda x, k: F.when(F.coalesce(F.get(rank, k + 1) != x, F.lit(True)), k + 1))
    docs = docs.withColumn("_ends", F.filter(ends, lambda x: x.isNotNull()))
    end = F.col("_ends")
    runs = F.transform("_ends", lambda e, k: F.struct(F.get(rank, e - 1), (e - F.coalesce(F.get(end, k - 1), F.lit(0))).cast("long")))
    docs = docs.withColumn("_runs", F.map_from_entries(runs))
    of = [F.coalesce(F.try_element_at("_runs", F.lit(i)), F.lit(0).cast("long")) for i in range(1, COMMON + 1)]
    return docs.withColumn("_tally", F.array(*of, (F.size("_words") - F.size("_rank")).cast("long"))).drop("_rank", "_ends", "_runs")


def js_distance(p: Column, q: Column) -> Column:
    """Base-2 Jensen-Shannon distance of two arrays of counts; null when either sums to zero."""
    total = lambda a: F.aggregate(a, F.lit(0.0), lambda s, x: s + x)
    share = lambda a: let(F.nullif(total(a), F.lit(0.0)), lambda t: F.transform(a, lambda x: x / t))
    half = lambda x, y: F.when(x > 0, x * F.log2(2 * x / (x + y))).otherwise(0.0)
    return F.sqrt(F.greatest(F.lit(0.0), total(F.zip_with(share(p), share(q), lambda x, y: (half(x, y) + half(y, x)) / 2))))


def measure(docs: DataFrame, carry: list[str] | None = None) -> DataFrame:
    """Per row: doc_id, the base counts, the distances _class_js and _word_js to the language's reference, and _row,
    a struct of the columns to carry, which are written with the counts so that no join has to find them again."""
    row = F.struct(*[F.col(f"`{c}`") for c in carry or ["doc_id"]]).alias("_row")
    docs = docs.select("doc_id", "text", "lang", row)
    refs = materialise(common_words(docs), "common-words")
    own = refs.where(F.col("_lang").isNotNull()).withColumnRenamed("_lang", "_ref")
    pooled = refs.where(F.col("_lang").isNull()).select(F.col("_common").alias("_c0"), F.col("_usual").alias("_u0"))
    out = docs.join(own, _lang(F.col("lang")) == F.col("_ref"), "left").join(F.broadcast(pooled), F.lit(True), "left")  # pooled: one row
    out = out.withColumns({"_common": F.coalesce("_common", "_c0"), "_usual": F.coalesce("_usual", "_u0")})
    out = with_tally(with_counts(out.select("doc_id", "text", "_row", "_ref", "_common", "_usual")))
    padded = F.transform(F.sequence(F.lit(1), F.lit(COMMON + 1)), lambda i: F.coalesce(F.get(F.col("_usual"), F.when(i <= COMMON, F.when(i < F.size("_usual"), i - 1).otherwise(-1)).otherwise(F.size("_usual") - 1)), F.lit(0)).cast("long"))
    rows = materialise(out.select("doc_id", "_row", "_ref", *COUNTS, "_chars", "_classes", "_tally", padded.alias("_usual")), "text-measures")
    first = _against(rows, rows.withColumn("_weight", F.lit(FULL)))
    near = F.lit(FULL) / (1 + F.pow(F.coalesce("_class_js", F.lit(0.0)) / HALF, F.lit(4)))
    return _against(rows, first.withColumn("_weight", F.round(near).cast("long")))


def _against(rows: DataFrame, weighted: DataFrame) -> DataFrame:
    """The distances of rows to the weighted class sums, by reference."""
    sums = F.array(*[F.sum(F.col("_classes")[i].cast("decimal(20,0)") * F.col("_weight")).cast("double") for i in range(CLASSES)]).alias("_normal")
    # written, so that its size is known when the join is planned
    own = materialise(weighted.where(F.col("_ref").isNotNull()).groupBy("_ref").agg(sums).withColumnRenamed("_ref", "_r"), "class-sums")
    every = weighted.agg(sums).withColumnRenamed("_normal", "_n0")
    out = rows.join(own, F.col("_ref") == F.col("_r"), "left").join(F.broadcast(every), F.lit(True), "left")  # every: one row
    return out.select("doc_id", "_row", "_ref", *COUNTS, "_chars", "_classes", "_tally", "_usual", js_distance(F.col("_classes"), F.coalesce("_normal", "_n0")).alias("_class_js"), js_distance(F.col("_tally"), F.col("_usual")).alias("_word_js"))


def judge(measured: DataFrame, max_class: float = MAX_CLASS_DISTANCE, max_word: float = MAX_WORD_DISTANCE, min_chars: int = MIN_CHARS, min_words: int = MIN_WORDS) -> DataFrame:
    failed = (F.col("n_words") < 50) | (100 * F.col("n_repeat_words") > 50 * F.col("n_words"))
    odd = ((F.col("_chars") >= min_chars) & (F.coalesce("_class_js", F.lit(0.0)) > max_class)) | ((F.col("n_words") >= min_words) & (F.coalesce("_word_js", F.lit(0.0)) > max_word))
    return measured.withColumns({"base_failed": failed, "kept": ~failed & ~odd})


def op7_quality_rules(spark: SparkSession, sf_dir: str) -> DataFrame:
    out = judge(measure(table(spark, sf_dir, "documents")))
    return out.select("doc_id", "n_words", "word_chars", "n_symbols", "n_dup_lines", "n_repeat_words", "base_failed", "kept", F.round("_class_js", 4).alias("class_distance"), F.round("_word_js", 4).alias("word_distance"))
