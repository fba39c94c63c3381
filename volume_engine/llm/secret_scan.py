"""Secret scan with a random forest that removes false positives, in DataFrame expressions only.

Candidates are all runs of at least twelve characters of the key alphabet with a digit in them, of
which a word (compact JSON, a query string) may hold several.  Each is described by its length, its character classes and the transitions between
them, the shares of it that listed words and words of the corpus's own dictionary cover, whether it
looks like a path, address or version, and the words around it.  A random forest (JVM) trained on
labelled findings decides.

The dictionary is all words of four letters or more that occur at least five times in the texts; it is
joined with the candidates' runs of letters, never collected.  Labelled findings come from the caller as
(candidate, glued, before, before2, after, label); where none are given, ``example_findings`` builds a
set from stated templates by rule.  ``held_out_quality`` tells what a forest trained on three quarters
of a set makes of the rest.

Defined results: null, blank and short texts have no candidates and give no row; a repeated row
repeats its findings; equal words at several places are several findings, and so are several runs of a word; an empty table gives an
empty result; extra columns are ignored.
"""

from __future__ import annotations

from pyspark.ml.classification import RandomForestClassificationModel, RandomForestClassifier
from pyspark.ml.feature import VectorAssembler
from pyspark.ml.functions import vector_to_array
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from .common import materialise, word_array

# Words that speak for or against a secret next to a candidate, and dictionary words inside one.
SECRET_WORDS = "token|secret|passwd|password|pwd|apikey|api_key|access_key|key|auth|bearer|credential|credentials|private"
DIGEST_WORDS = "commit|sha|sha1|sha256|md5|checksum|hash|digest|revision|rev|etag|uuid|guid|id|version|build|serial|isbn|phone|tel|card|order|invoice"
PLACEHOLDERS = "example|sample|dummy|changeme|placeholder|your|test|todo|none|null|xxxx+|1234567890|abcdef|foo|bar"
DICTIONARY = "the|and|for|with|from|this|that|have|will|page|file|user|name|data|info|image|index|main|home|docs|http|https|www|com|org|net|example|sample|test|dummy|token|secret|password|key|change|me|your|here|value|default|config|static|public|assets|mail|server|version|release|build|commit"
RUN = "[A-Za-z0-9+/_.\\\\-]{12,}"
FEATURES = ["length", "digits", "capitals", "marks", "hex", "transitions", "repeats", "covered", "spelled", "pathlike", "dotted", "placeholder", "assigned", "quoted", "secret_near", "secret_next", "digest_near", "all_digits", "groups"]


def candidates(docs: DataFrame) -> DataFrame:
    """doc_id, at (word number), candidate, glued (what stands before it in the word, from the run before on), before, before2, after."""
    words = docs.select("doc_id", word_array(F.col("text")).alias("words"))
    hits = f"filter(sequence(0, size(words)), i -> length(get(words, i)) >= 12 and get(words, i) rlike '[0-9]' and get(words, i) rlike '{RUN}')"
    places = words.select("doc_id", F.expr(f"transform({hits}, i -> struct(i as at, words[i] as word, coalesce(get(words, i - 1), '') as before, coalesce(get(words, i - 2), '') as before2, coalesce(get(words, i + 1), '') as after))").alias("places"))
    # the outer form keeps a filter from being pushed below the word arrays
    found = places.select("doc_id", F.explode_outer("places").alias("p")).select("doc_id", "p.*").filter("at is not null")
    # gaps[k] stands before runs[k]; a run that a sign of assignment follows is the name of the next one
    cut = found.withColumns({"runs": F.expr(f"regexp_extract_all(word, '{RUN}', 0)"), "gaps": F.expr(f"split(word, '{RUN}')")})
    name = "case when k > 0 and gaps[k] rlike '^[\"\\'`]?[=:]' then regexp_extract(runs[k - 1], '[A-Za-z0-9_-]*$', 0) else '' end"
    each = cut.withColumn("r", F.explode(F.expr(f"filter(transform(runs, (run, k) -> struct(run as candidate, concat({name}, gaps[k]) as glued)), r -> r.candidate rlike '[0-9]')")))
    return each.select("doc_id", "at", "r.candidate", "r.glued", "before", "before2", "after")


def dictionary(docs: DataFrame, least: int = 5) -> DataFrame:
    """``word``: lower-cased words of at least four letters that occur ``least`` times or more in the texts."""
    words = docs.select(F.explode_outer(word_array(F.lower(F.col("text")))).alias("word")).filter("length(word) >= 4 and word rlike '^[a-z]{4,}[.,;:!?]?$'")
    words = words.select(F.expr("rtrim('.,;:!?', word)").alias("word")).filter("length(word) >= 4")
    return words.groupBy("word").agg(F.count("*").alias("n")).filter(F.col("n") >= least).select("word")


def spelled(findings: DataFrame, known: DataFrame) -> DataFrame:
    """``findings`` with ``spelled``: the share of the candidate in runs of letters that the dictionary knows.

    Runs end where a small letter is followed by a capital one.
    """
    runs = F.expr("regexp_extract_all(lower(regexp_replace(candidate, '([a-z])([A-Z])', '$1 $2')), '[a-z]{4,}', 0)")
    parts = findings.select("candidate").distinct().select("candidate", F.posexplode(runs).alias("k", "word"))
    found = parts.join(known, "word", "left_semi").groupBy("candidate").agg(F.sum(F.length("word")).alias("letters"))
    share = F.coalesce("letters", F.lit(0)) / F.greatest(F.length("candidate"), F.lit(1))
    return findings.join(found, "candidate", "left").withColumn("spelled", share.cast("double")).drop("letters")


def described(findings: DataFrame) -> DataFrame:
    """``findings`` (with ``spelled``) with the forest's features."""
    c, n = "candidate", "greatest(length(candidate), 1)"
    near = "lower(concat_ws(' ', before2, before, glued))"
    expressions = {
        "length": f"cast(length({c}) as double)",
        "digits": f"regexp_count({c}, '[0-9]') / {n}",
        "capitals": f"regexp_count({c}, '[A-Z]') / {n}",
        "marks": f"regexp_count({c}, '[^A-Za-z0-9]') / {n}",
        "hex": f"cast({c} rlike '^[0-9a-fA-F]+$' as double)",
        "transitions": f"regexp_count({c}, '(?<=[0-9])(?=[A-Za-z])|(?<=[A-Za-z])(?=[0-9])|(?<=[a-z])(?=[A-Z])') / {n}",
        "repeats": f"regexp_count({c}, '(.)\\\\1') / {n}",
        "covered": f"(length({c}) - length(regexp_replace(lower({c}), '{DICTIONARY}', ''))) / {n}",
        "pathlike": f"cast(regexp_count({c}, '/') >= 2 or glued rlike '//|[a-z]/$' as double)",
        "dotted": f"cast({c} rlike '^[A-Za-z0-9_-]+([.][A-Za-z0-9_-]+)+$' as double)",
        "placeholder": f"cast(lower({c}) rlike '{PLACEHOLDERS}' as double)",
        "assigned": "cast(before rlike '[=:]$' or glued rlike '[=:][\"\\']?$' as double)",
        "quoted": "cast(glued rlike '[\"\\'`]$' as double)",
        "secret_near": f"cast({near} rlike '(^|[^a-z])({SECRET_WORDS})([^a-z]|$)' as double)",
        "secret_next": f"cast(lower(after) rlike '(^|[^a-z])({SECRET_WORDS})([^a-z]|$)' as double)",
        "digest_near": f"cast({near} rlike '(^|[^a-z])({DIGEST_WORDS})([^a-z]|$)' as double)",
        "all_digits": f"cast({c} rlike '^[0-9.-]+$' as double)",
        "groups": f"cast(size(split({c}, '[-_./+]')) as double)",
    }
    return findings.withColumns({k: F.expr(v).cast("double") for k, v in expressions.items()})


def example_findings(spark: SparkSession, rows: int = 6000, seed: int = 11) -> DataFrame:
    """Labelled findings by rule: random keys in assignments (1), and digests, numbers, addresses, paths, versions and placeholders (0)."""
    noise = f"sha2(concat('{seed}:', id), 256)"
    key64 = f"translate(substr(base64(unhex({noise})), 1, 40), '=', 'A')"
    word = "element_at(array('then', 'retion', 'der', 'que', 'with', 'los', 'values', 'page', 'and', 'see'), cast(id div 7 % 10 + 1 as int))"
    name = "element_at(array('token', 'secret', 'api_key', 'password', 'auth', 'access_key', 'TOKEN', 'key'), cast(id div 11 % 8 + 1 as int))"
    digest = "element_at(array('commit', 'sha256', 'md5', 'checksum', 'revision', 'etag', 'uuid'), cast(id div 13 % 7 + 1 as int))"
    size = "cast(20 + id div 17 % 5 * 5 as int)"
    digits = f"translate(substr({noise}, 1, 16), 'abcdef', '012345')"
    kinds = [
        (f"substr({noise}, 1, {size})", "'\"'", "'='", name, 1),
        (f"substr({noise}, 1, 40)", "'\"'", "'='", name, 1),
        (f"substr({key64}, 1, {size})", f"concat({name}, '=')", word, word, 1),
        (f"substr({key64}, 1, {size})", "''", f"concat({name}, ':')", word, 1),
        (f"concat('sk_', substr({key64}, 1, 24))", "''", word, word, 1),
        (f"substr({noise}, 1, 40)", "''", digest, word, 0),
        (f"concat_ws('-', substr({noise}, 1, 8), substr({noise}, 9, 4), substr({noise}, 13, 4), substr({noise}, 17, 4), substr({noise}, 21, 12))", "''", word, word, 0),
        (digits, "''", word, word, 0),
        (f"concat('+1-', substr({digits}, 1, 3), '-555-', substr({digits}, 4, 4))", "''", word, word, 0),
        (f"concat('mail', id % 10, '.example.com')", f"concat({word}, '.', id % 90, '@')", word, word, 0),
        (f"concat('static/assets/', {word}, '/', id % 100, '.png')", "'/'", word, word, 0),
        (f"concat('10.', id % 250, '.', id % 13, '.', id % 200 + 100)", "''", word, word, 0),
        (f"concat('your_', {name}, '_here_123')", "'\"'", "'='", name, 0),
        (f"concat('example', repeat('1234', 4))", "'\"'", "'='", name, 0),
        (f"concat('release-', id % 9, '.', id % 20, '.', id % 50, '-build')", "''", "'version'", word, 0),
        (f"concat({word}, {word}, {word}, id % 90)", "''", word, word, 0),
    ]

    def pick(k: int) -> str:
        return "case id % 16 " + " ".join(f"when {i} then {x[k]}" for i, x in enumerate(kinds)) + " end"

    base = spark.range(rows)
    return base.select(F.expr(pick(0)).alias("candidate"), F.expr(pick(1)).alias("glued"), F.expr(pick(2)).alias("before"), F.expr(pick(3)).alias("before2"), F.expr(word).alias("after"), F.expr(pick(4)).cast("double").alias("label"))


def train(labelled: DataFrame, known: DataFrame, trees: int = 30, depth: int = 7, seed: int = 5) -> RandomForestClassificationModel:
    ready = VectorAssembler(inputCols=FEATURES, outputCol="features").transform(described(spelled(labelled, known))).select("features", "label")
    # the forest samples rows by their place, so they are put in one order
    return RandomForestClassifier(numTrees=trees, maxDepth=depth, seed=seed, featureSubsetStrategy="sqrt").fit(ready.orderBy(F.xxhash64("features"), "label").coalesce(1))


def judged(findings: DataFrame, model: RandomForestClassificationModel, known: DataFrame, threshold: float) -> DataFrame:
    ready = VectorAssembler(inputCols=FEATURES, outputCol="features").transform(described(spelled(findings, known)))
    scored = model.transform(ready).withColumn("score", F.round(vector_to_array("probability")[1], 6))
    return scored.withColumn("secret", F.col("score") >= threshold)


def held_out_quality(labelled: DataFrame, known: DataFrame, threshold: float = 0.5) -> dict[str, float]:
    """Precision and recall on the quarter of the labelled findings that a hash of the candidate holds out."""
    held = F.crc32(F.col("candidate").cast("binary")) % 4 == 0
    model = train(labelled.filter(~held), known)
    said, is_one = F.col("secret"), F.col("label") == 1
    r = judged(labelled.filter(held), model, known, threshold).agg(F.count_if(said & is_one), F.count_if(said), F.count_if(is_one), F.count("*")).first()
    return {"precision": r[0] / max(1, r[1]), "recall": r[0] / max(1, r[2]), "findings": r[3]}


def scan_secrets(docs: DataFrame, labelled: DataFrame | None = None, threshold: float = 0.5) -> DataFrame:
    """Every candidate of ``docs`` (doc_id, text) with the forest's ``score`` and verdict ``secret``."""
    known = materialise(dictionary(docs), "secret-dictionary")
    found = materialise(candidates(docs), "secret-candidates")
    model = train(example_findings(docs.sparkSession) if labelled is None else labelled, known)
    return judged(found, model, known, threshold).select("doc_id", F.col("at").cast("long").alias("at"), "candidate", F.col("length").cast("long").alias("length"), "score", "secret")


def op4_secret_forest(spark, sf_dir) -> DataFrame:
    found = scan_secrets(spark.read.parquet(f"{sf_dir}/documents.parquet").select("doc_id", "text"))
    return found.select("doc_id", "at", F.sha2("candidate", 256).alias("candidate_sha256"), "length", "score", "secret")
