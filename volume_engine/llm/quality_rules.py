"""Quality rules under weak supervision, in DataFrame expressions only.

Every rule looks at one measure of a text and votes good (1), bad (-1) or abstains (0).  The
accuracies of the rules are unknown: expectation-maximisation over the counts of the vote patterns
(at most 3^rules rows, whatever the corpus) estimates each rule's vote distribution in good and in
bad texts, and a text's posterior probability of being good decides.  All measures are computed
row by row on the whole text with built-in functions, so nothing but pattern counts is shuffled.

Defined results: a null or blank text has no words, fails the base rule and is not kept; equal
texts get equal verdicts; an empty table gives an empty result; extra columns pass through.  A
three-word window is recognised by its 64-bit hash.  Words are runs of characters other than 0x20
and 0x09-0x0D; texts keep their case.
"""

from __future__ import annotations

import math
from dataclasses import dataclass

from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

from .common import materialise, word_array

POSITION_BITS = 28  # a text of 2 GB has fewer than 2^28 three-word windows of any use


@dataclass(frozen=True)
class Rule:
    """Votes bad where ``bad`` holds, good where ``good`` holds, else abstains (SQL over the measures)."""

    name: str
    bad: str
    good: str


#: Fault finders vote bad or abstain; only the two rules on plain prose also vote good.
RULES = (
    Rule("plain_words", "n_plain < 0.6 * n_words", "n_plain >= 0.85 * n_words"),
    Rule("sentences", "200 * n_ends < n_words", "60 * n_ends >= n_words and 3 * n_ends <= n_words"),
    Rule("symbols", "n_symbols > 0.1 * n_words", "false"),
    Rule("repeated_words", "n_repeat_words > 0.3 * n_words", "false"),
    Rule("repeated_lines", "n_dup_lines > 0.3 * n_lines", "false"),
    Rule("word_length", "word_chars < 2.5 * n_words or word_chars > 12 * n_words", "false"),
    Rule("capitals", "n_capitals > 0.3 * word_chars", "false"),
    Rule("exclamations", "n_shouts > 0.1 * n_words", "false"),
)
#: Sentence ends of other scripts, which may stand behind a blank or have no blank behind them, and their lesser marks.
OTHER_ENDS = "\u0589\u061f\u06d4\u0964\u0965\u104b\u1362\u1367\u17d4\u3002\uff01\uff1f\uff61"
OTHER_MARKS = "\u060c\u061b\u104a\u1363\u3001\uff0c\uff1a\uff1b"
#: Letters with their marks, at most the first of them a capital, with at most one mark of punctuation behind; marks of scripts without blanks may stand inside.
OTHER_PART = f"\\p{{Lo}}\\p{{Lm}}\\p{{M}}\\u200c\\u200d{OTHER_ENDS}{OTHER_MARKS}"
PLAIN_WORD = f"(?<![^ \\t-\\r])\\p{{L}}\\p{{Ll}}*+(?:[{OTHER_PART}][\\p{{Ll}}{OTHER_PART}]*+)?+[.,;:]?+(?![^ \\t-\\r])"
#: What is rare is tested first in both.
SENTENCE_END = "[.!?](?<=[\\p{L}\\p{M}].)(?![^ \\t-\\r])"
OTHER_END = f"[\\u0589-\\uffff&&[{OTHER_ENDS}]]"
BASE_FAILED = "n_words < 50 or 100 * n_repeat_words > 50 * n_words"


def measures(docs: DataFrame, text: str = "text") -> DataFrame:
    """``docs`` with its measure columns; names with a ``_q_`` prefix are working columns and are dropped."""
    low = (1 << POSITION_BITS) - 1
    body = F.coalesce(F.col(text), F.lit(""))
    df = docs.withColumn("_q_words", word_array(F.col(text)))
    df = df.withColumn("n_words", F.size("_q_words").cast("long"))
    windows = "if(n_words < 3, cast(array() as array<bigint>), transform(sequence(0, cast(n_words - 3 as int)), i -> xxhash64(_q_words[i], _q_words[i + 1], _q_words[i + 2])))"
    df = df.withColumn("_q_hash", F.expr(windows))
    # window hashes sorted with their positions packed below; equal windows become neighbours
    df = df.withColumn("_q_sorted", F.expr(f"sort_array(transform(_q_hash, (h, i) -> shiftleft(h, {POSITION_BITS}) | cast(i as bigint)))"))

    def same(offset: int) -> str:
        other = f"get(_q_sorted, k + {offset})"
        return f"coalesce(shiftright(x ^ {other}, {POSITION_BITS}) = 0 and get(_q_hash, cast(x & {low} as int)) = get(_q_hash, cast({other} & {low} as int)), false)"

    repeated = f"filter(_q_sorted, (x, k) -> {' or '.join(same(o) for o in (-1, 1, -2, 2))})"
    df = df.withColumn("_q_repeat", F.expr(f"sort_array(transform({repeated}, x -> x & {low}))"))
    covered = "aggregate(transform(_q_repeat, (x, k) -> least(3L, coalesce(get(_q_repeat, k + 1) - x, 3L))), 0L, (a, x) -> a + x)"
    lines = F.filter(F.split(body, "\n"), lambda x: F.rlike(x, F.lit("[^ \\t-\\r]")))
    df = df.withColumn("_q_lines", lines)
    out = {
        "word_chars": F.length(F.array_join("_q_words", "")).cast("long"),
        "n_symbols": F.regexp_count(body, F.lit("[#*$%&|<>]")).cast("long"),
        "n_dup_lines": (F.size("_q_lines") - F.size(F.array_distinct("_q_lines"))).cast("long"),
        "n_repeat_words": F.expr(covered),
        "n_lines": F.size("_q_lines").cast("long"),
        "n_capitals": F.regexp_count(body, F.lit("\\p{Lu}")).cast("long"),
        "n_plain": F.regexp_count(body, F.lit(PLAIN_WORD)).cast("long"),
        "n_ends": (F.regexp_count(body, F.lit(SENTENCE_END)) + F.regexp_count(body, F.lit(OTHER_END))).cast("long"),
        "n_shouts": F.regexp_count(body, F.lit("!+")).cast("long"),
    }
    return df.withColumns(out).drop("_q_words", "_q_hash", "_q_sorted", "_q_repeat", "_q_lines")


def votes(rules=RULES) -> dict[str, Column]:
    return {f"vote_{r.name}": F.expr(f"case when {r.bad} then -1 when {r.good} then 1 else 0 end") for r in rules}


@dataclass(frozen=True)
class LabelModel:
    """Share of good texts and, per rule, the probabilities of the votes (-1, 0, 1) in bad and good texts."""

    prior: float
    bad: tuple[tuple[float, float, float], ...]
    good: tuple[tuple[float, float, float], ...]

    def log_odds(self, rules=RULES) -> Column:
        total = F.lit(math.log(self.prior / (1 - self.prior)))
        for rule, bad, good in zip(rules, self.bad, self.good, strict=True):
            vote = F.col(f"vote_{rule.name}")
            ratio = [math.log(g / b) for b, g in zip(bad, good, strict=True)]
            total += F.when(vote == -1, ratio[0]).when(vote == 0, ratio[1]).otherwise(ratio[2])
        return total


def fit_label_model(patterns: list[tuple[tuple[int, ...], int]], n_rules: int, iterations: int = 50, pull: float = 0.01) -> LabelModel:
    """Expectation-maximisation from vote-pattern counts.

    ``pull`` weighs the starting belief (a rule that votes is right nine times in ten) as a share
    of the texts, so the fit is the same for a corpus and for two copies of it, and the two classes
    keep their meaning.
    """
    total = sum(c for _, c in patterns)
    if not total:
        patterns, total = [((0,) * n_rules, 1)], 1
    start = {}
    for j in range(n_rules):
        abstain = sum(c for p, c in patterns if p[j] == 0) / total
        abstain = min(max(abstain, 0.01), 0.98)
        start[j] = ((0.9 * (1 - abstain), abstain, 0.1 * (1 - abstain)), (0.1 * (1 - abstain), abstain, 0.9 * (1 - abstain)))
    bad, good, prior = [start[j][0] for j in range(n_rules)], [start[j][1] for j in range(n_rules)], 0.5
    for _ in range(iterations):
        mass = [[[pull * total * start[j][y][v] for v in range(3)] for j in range(n_rules)] for y in (0, 1)]
        good_mass = 0.0
        for pattern, count in patterns:
            odds = math.log(prior / (1 - prior)) + sum(math.log(good[j][v + 1] / bad[j][v + 1]) for j, v in enumerate(pattern))
            p = 1 / (1 + math.exp(-max(min(odds, 500), -500)))
            good_mass += count * p
            for j, v in enumerate(pattern):
                mass[1][j][v + 1] += count * p
                mass[0][j][v + 1] += count * (1 - p)
        prior = min(max(good_mass / total, 1e-3), 1 - 1e-3)
        bad, good = ([tuple(x / sum(m) for x in m) for m in mass[y]] for y in (0, 1))
    return LabelModel(prior, tuple(bad), tuple(good))


def judge(docs: DataFrame, rules=RULES, text: str = "text", threshold: float = 0.5, keep_text: bool = True) -> DataFrame:
    """``docs`` with measures, votes, ``base_failed``, ``p_good`` and ``kept``; without its text unless ``keep_text``.

    The measured rows are written once to the shared folder; the pattern counts and the verdicts
    both read them there, so the texts are measured once.
    """
    measured = measures(docs, text).withColumns(votes(rules))
    measured = materialise(measured if keep_text else measured.drop(text), "quality")
    names = [f"vote_{r.name}" for r in rules]
    counted = measured.groupBy(*names).count().collect()  # at most 3^rules rows
    model = fit_label_model([(tuple(r[n] for n in names), r["count"]) for r in counted], len(rules))
    p_good = 1 / (1 + F.exp(-model.log_odds(rules)))
    judged = measured.withColumns({"base_failed": F.expr(BASE_FAILED), "p_good": p_good})
    return judged.withColumn("kept", ~F.col("base_failed") & (F.col("p_good") >= threshold))


def op8_quality_votes(spark, sf_dir) -> DataFrame:
    docs = spark.read.parquet(f"{sf_dir}/documents.parquet").select("doc_id", "text")
    columns = ["doc_id", "n_words", "word_chars", "n_symbols", "n_dup_lines", "n_repeat_words", "base_failed", "kept"]
    return judge(docs, keep_text=False).select(*columns, F.round("p_good", 6).alias("p_good"))
