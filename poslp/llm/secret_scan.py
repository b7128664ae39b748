"""Secret scanning with a random forest that removes false positives.

Candidates are all runs of 16 or more key-like characters inside the words of a text; a run is cut after an equals sign
that more than padding follows, so that an assigned value stands apart from its name. Features: length, character
transitions (the share of each change between lower case, upper case, digits and marks, and the number of changes),
shares of digits and capitals, distinct characters, how much of the candidate the corpus's own frequent words cover,
marks of the document's path (its source), and the neighbouring words. A random forest, trained from labelled findings,
scores each candidate.

Findings can be given with labels. The default labels come from verifiers of high precision: a value of a known key
shape that is assigned to a credential name is a secret; a candidate that is all digits, or that the dictionary
covers for the most part, is none; others stay unlabelled and are only scored. The forest sees at most
``TRAIN_ROWS`` labelled findings, a documented bound: a hashed draw of findings from each label, half of the bound or
what the other label leaves, weighted by the share drawn; dictionary and candidates come from all documents. Everything on the main path is DataFrame functions and JVM forests.

Defined results: null or empty text has no candidates; repeated rows give repeated findings; an empty table, or one
without both labels, gives no score above zero but the verified ones; other columns take no part.
"""

from __future__ import annotations

from pyspark.ml.classification import RandomForestClassifier
from pyspark.ml.feature import VectorAssembler
from pyspark.ml.functions import vector_to_array
from pyspark.sql import Column, DataFrame, SparkSession
from pyspark.sql import functions as F

from poslp.llm.common import LOWER, UPPER, materialise, table, words

#: A run ends at an equals sign unless only equals signs follow, as in padded base 64.
CANDIDATE = r"[A-Za-z0-9+/_-]{16,}(?:=+(?![A-Za-z0-9+/_-]))?"
TRAIN_ROWS = 20_000
DICTIONARY = 400
#: Characters of its word seen before and after a candidate.
NEAR = 80
#: Names a credential is assigned to, and marks of a path that holds examples.
NAMES = r"(?i)(token|secret|passw|api_?key|access_?key|auth|credential|private_?key)"
EXAMPLE_PATH = r"(?i)(test|example|sample|fixture|doc)"
#: Shapes of keys that are verified by form alone.
SHAPES = r"^([0-9a-f]{32}|[0-9a-f]{40}|[0-9a-f]{64}|AKIA[0-9A-Z]{16}|gh[pousr]_[A-Za-z0-9]{36}|sk-[A-Za-z0-9]{20,}|[A-Za-z0-9+/]{40,}={0,2})$"
#: The classes of characters, and the pairs of them whose share of a candidate's neighbours is a feature.
KINDS = "lud-"
PAIRS = [a + b for a in KINDS for b in KINDS]
FEATURES = [f"pair_{p}" for p in PAIRS] + ["length", "changes", "digits", "capitals", "marks", "distinct", "covered", "example_path", "path_depth", "named", "assigned", "quoted", "prose_before", "prose_after"]


def candidates(docs: DataFrame) -> DataFrame:
    """doc_id, place (word number from 0), offset (in the word), _path, candidate, the word's text just before and after
    it, and the words around, of which those before count for the first run of a word alone."""
    docs = docs.select("doc_id", F.coalesce("source", F.lit("")).alias("_path"), words(F.col("text")).alias("_w"))
    hits = F.filter(F.transform("_w", lambda w, i: F.when(F.length(w) >= 16, F.struct(i.alias("place"), F.regexp_extract_all(w, F.lit(CANDIDATE), F.lit(0)).alias("runs")))), lambda x: x.isNotNull() & (F.size(x["runs"]) > 0))
    near = lambda x, k: F.coalesce(F.get("_w", x["place"] + k), F.lit(""))
    full = F.transform(hits, lambda x: F.struct(x["place"], x["runs"], F.split(F.get("_w", x["place"]), CANDIDATE, -1).alias("gaps"), near(x, -2).alias("b2"), near(x, -1).alias("b1"), near(x, 1).alias("a1")))
    found = docs.select("doc_id", "_path", F.explode(full).alias("_x")).select("doc_id", "_path", "_x.*")
    runs, gaps = F.col("runs"), F.col("gaps")
    ends = F.aggregate(F.zip_with(F.transform(gaps, F.length), F.transform(runs, F.length), lambda g, r: g + F.coalesce(r, F.lit(0))), F.array(F.lit(0)), lambda e, n: F.array_append(e, F.element_at(e, -1) + n))
    found = found.withColumn("_ends", ends).select("*", F.posexplode("runs").alias("_k", "candidate"))
    first, gap = F.col("_k") == 0, F.get(gaps, F.col("_k"))
    before = F.right(F.concat(F.coalesce(F.right(F.get(runs, F.col("_k") - 1), F.lit(NEAR)), F.lit("")), gap), F.lit(NEAR))
    return found.select(
        "doc_id", "_path", "place", (F.get("_ends", F.col("_k")) + F.length(gap)).alias("offset"), "candidate", before.alias("before"),
        F.left(F.get(gaps, F.col("_k") + 1), F.lit(NEAR)).alias("after"), *[F.when(first, F.col(c)).otherwise("").alias(c) for c in ("b2", "b1")], "a1",
    )


def dictionary(docs: DataFrame) -> list[str]:
    """The most frequent words of three or more letters over all documents; DICTIONARY rows reach the driver."""
    counts = docs.select(F.explode(words(F.col("text"))).alias("w")).where(F.col("w").rlike(r"^\p{L}{3,12}$"))
    counts = counts.groupBy("w").agg(F.count(F.lit(1)).alias("n"))
    return [r["w"] for r in counts.orderBy(F.desc("n"), "w").limit(DICTIONARY).collect()]


def _share(text: Column, pattern: str) -> Column:
    return (F.length(text) - F.length(F.regexp_replace(text, pattern, ""))) / F.length(text)


def with_features(found: DataFrame, known: list[str]) -> DataFrame:
    c = F.col("candidate")
    kinds = F.translate(c, LOWER + UPPER + "0123456789+/_=-", "l" * 26 + "u" * 26 + "d" * 10 + "-" * 5)
    pairs = F.transform(F.sequence(F.lit(1), F.length("_kinds") - 1), lambda i: F.substring("_kinds", i, F.lit(2)))
    lower = sorted({w.lower() for w in known}, key=lambda w: (-len(w), w))
    rest = F.regexp_replace(F.lower(c), "|".join(lower), "") if lower else c
    prose = r"^\p{L}{1,12}[.,]?$"
    found = found.withColumn("_kinds", kinds).withColumn("_pairs", pairs)
    share = lambda p: F.size(F.filter("_pairs", lambda x: x == p)) / F.size("_pairs")
    return found.withColumns({
        **{f"pair_{p}": share(p) for p in PAIRS},
        "length": F.length(c).cast("double"),
        "changes": F.size(F.filter("_pairs", lambda x: F.substring(x, 1, 1) != F.substring(x, 2, 1))).cast("double"),
        "digits": _share(c, "[0-9]"), "capitals": _share(c, "[A-Z]"), "marks": _share(c, "[+/_=-]"),
        "distinct": F.size(F.array_distinct(F.split(c, ""))).cast("double"),
        "covered": 1 - F.length(rest) / F.length(c),
        "example_path": F.col("_path").rlike(EXAMPLE_PATH).cast("double"),
        "path_depth": (F.length("_path") - F.length(F.replace("_path", F.lit("/")))).cast("double"),
        "named": (F.concat("before", "candidate").rlike(NAMES) | F.col("b1").rlike(NAMES) | F.col("b2").rlike(NAMES)).cast("double"),
        "assigned": (((F.col("offset") == F.length("before")) & F.concat("before", "candidate").rlike("^[A-Za-z_]+[=:]")) | F.col("before").rlike("[=:][\"'`]*$") | F.col("b1").rlike("[=:]$")).cast("double"),
        "quoted": F.concat("before", "after").rlike("[\"'`]").cast("double"),
        "prose_before": F.col("b1").rlike(prose).cast("double"), "prose_after": F.col("a1").rlike(prose).cast("double"),
    }).drop("_kinds", "_pairs")


def verified_labels(found: DataFrame) -> DataFrame:
    """found with _label: 1.0, 0.0 or null."""
    shaped = F.col("candidate").rlike(SHAPES) & F.col("candidate").rlike("[0-9]") & F.col("candidate").rlike("[A-Za-z]")
    yes = shaped & (F.col("named") == 1) & (F.col("assigned") == 1) & (F.col("covered") < 0.5)
    no = (F.col("digits") == 1) | ((F.col("covered") >= 0.5) & (F.col("named") == 0))
    return found.withColumn("_label", F.when(yes, 1.0).when(no, 0.0))


def training_rows(labelled: DataFrame) -> DataFrame:
    """FEATURES, _label and _weight of at most TRAIN_ROWS labelled findings, drawn from each label by the hash of the finding."""
    whole = {r["_label"]: r["count"] for r in labelled.groupBy("_label").count().collect()}  # two rows
    lot = F.xxhash64(*([c for c in ("doc_id", "place", "offset", "candidate") if c in labelled.columns] or FEATURES))
    out = labelled.select(*FEATURES, "_label", F.lit(1.0).alias("_weight")).limit(0)
    for label, n in sorted(whole.items()):
        take = min(n, max(TRAIN_ROWS // 2, TRAIN_ROWS - (sum(whole.values()) - n)))
        drawn = labelled.where(F.col("_label") == label).orderBy(lot, *FEATURES).limit(take)
        out = out.unionByName(drawn.select(*FEATURES, "_label", F.lit(n / take).alias("_weight")))
    return out


def secret_scan(docs: DataFrame, labelled: DataFrame | None = None, trees: int = 20, depth: int = 6, seed: int = 7) -> DataFrame:
    """The findings with features and ``score``. labelled: rows of FEATURES and _label (doc_id, place, offset
    and candidate tell equal ones apart), by default the verified ones."""
    docs = docs.select("doc_id", "source", "text")
    found = materialise(verified_labels(with_features(candidates(docs), dictionary(docs))), "findings")
    train = (labelled if labelled is not None else found).where(F.col("_label").isNotNull())
    train = materialise(training_rows(train), "labelled-findings")
    if train.agg(F.count_distinct("_label")).first()[0] < 2:
        return found.withColumn("score", F.coalesce("_label", F.lit(0.0)))
    assemble = VectorAssembler(inputCols=FEATURES, outputCol="_features", handleInvalid="keep")
    forest = RandomForestClassifier(featuresCol="_features", labelCol="_label", weightCol="_weight", probabilityCol="_p", rawPredictionCol="_raw", predictionCol="_class", numTrees=trees, maxDepth=depth, seed=seed)
    scored = forest.fit(assemble.transform(train)).transform(assemble.transform(found))
    return scored.withColumn("score", vector_to_array("_p")[1]).drop("_features", "_raw", "_p", "_class")


def op2_secret_scan(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Every candidate of every document, its digest in place of its text, and the forest's verdict."""
    out = secret_scan(table(spark, sf_dir, "documents"))
    return out.select("doc_id", F.col("place").cast("long").alias("word_place"), F.col("offset").cast("long").alias("word_offset"), F.col("length").cast("long").alias("n_chars"), F.sha2("candidate", 256).alias("candidate_sha256"), F.round("score", 6).alias("score"), (F.col("score") >= 0.5).alias("is_secret"))
