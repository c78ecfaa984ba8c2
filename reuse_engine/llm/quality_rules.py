"""Quality rules under weak supervision.

Each rule votes that a document is good (1), bad (0), or abstains (null).  Votes
are reduced to patterns with counts, at most ``3 ** rules`` rows at any corpus
size, and expectation-maximisation on that table estimates how often each rule
votes rightly on good and on bad documents, and the share of good ones.  The
posterior probability of being good replaces the demand that all rules pass.
Texts that fail the base rules are out in any case and do not enter the estimate,
so that the model learns the junk which the base rules do not know.  The rules
are graded well inside what the base rules pass and look at different sides of a
text, so that they can disagree: one that many good documents break is found to
say little, and a document is dropped by the weight of its votes.  Estimates are
smoothed by ``PRIOR_VOTES`` and have no other bound.

All text measures are built-in column functions, evaluated once per row without
a shuffle; the only exchange is the count of vote patterns.
"""

from __future__ import annotations

import math
from dataclasses import dataclass

from pyspark.sql import Column, DataFrame, SparkSession
from pyspark.sql import functions as F

from reuse_engine.llm.native_text import lines, window_hashes, words
from reuse_engine.storage import materialize, spread

#: Fixed values of the base rules.
MIN_WORDS, MAX_REPEAT_SHARE = 10, 20
#: Smallest posterior that is kept.
KEEP_FROM = 0.5
ROUNDS, SETTLED = 60, 1e-5
#: Start of the estimation: share of good documents, and how often a vote is right on good and on bad ones.
START_GOOD, START_RIGHT_GOOD, START_RIGHT_BAD = 0.9, 0.95, 0.5
#: Pseudo-votes that hold an accuracy near its start when few documents vote.
PRIOR_VOTES = 10.0

#: Function words of the languages of the corpus; fixed values.
COMMON_WORDS = [
    "the", "of", "and", "to", "in", "is", "that", "it", "was", "for", "on", "are", "as", "with", "be", "at", "by", "this", "from",
    "der", "die", "das", "und", "den", "von", "zu", "mit", "ist", "im", "für", "auf", "eine", "ein", "dem", "nicht",
    "le", "la", "les", "de", "des", "et", "un", "une", "est", "que", "qui", "dans", "pour", "sur", "par", "pas", "au", "du",
    "el", "los", "las", "y", "se", "del", "una", "por", "con", "para", "su", "al", "es", "no", "lo",
]


def measured(docs: DataFrame, id_col: str = "doc_id", text_col: str = "text") -> DataFrame:
    """``id_col`` and the measures of each whole text; null text counts as empty."""
    text = F.coalesce(F.col(text_col), F.lit(""))
    base = spread(docs.select(F.col(id_col), F.col(text_col))).select(F.col(id_col).alias("id"), text.alias("text"))
    split = base.withColumn("w", words(F.col("text"))).withColumn("ls", lines(F.col("text")))
    hashed = split.withColumn("h", F.when(F.size("w") >= 5, window_hashes("w")).otherwise(F.array().cast("array<bigint>")))
    n = F.size("w").cast("long")
    return hashed.select(
        "id",
        n.alias("n_words"),
        F.length(F.array_join("w", "")).cast("long").alias("word_chars"),
        F.regexp_count("text", F.lit(r"[#*$%&|<>]")).cast("long").alias("n_symbols"),
        (F.size("ls") - F.size(F.array_distinct("ls"))).cast("long").alias("n_dup_lines"),
        repeated_words("h").alias("n_repeat_words"),
        F.size("ls").cast("long").alias("n_lines"),
        F.size(F.array_distinct("w")).cast("long").alias("n_distinct"),
        F.regexp_count("text", F.lit(r"\p{Lu}")).cast("long").alias("n_upper"),
        F.size(F.filter("w", lambda x: F.lower(x).isin(COMMON_WORDS))).cast("long").alias("n_common"),
        (F.length("text") - F.length(F.translate("text", "0123456789", ""))).cast("long").alias("n_digits"),
        F.size(F.filter("w", lambda x: F.length(x) == 1)).cast("long").alias("n_single"),
        F.size(F.filter("w", lambda x: x.rlike(r"\p{L}"))).cast("long").alias("n_lettered"),
        F.size(F.filter("ls", lambda x: x.rlike(r"[.!?:;][\x20\x09-\x0D]*$"))).cast("long").alias("n_closed"),
    )


def repeated_words(hashes: str) -> Column:
    """Words in five-word windows that occur twice or more, the first included.

    ``hashes``: a 64-bit hash per window, in order.  Only texts with a repeat are
    sorted; covered words are the union of the windows' spans, taken in order.
    """
    h = F.col(hashes)
    placed = F.sort_array(F.transform(h, lambda x, i: F.struct(x.alias("x"), i.alias("i"))))
    twin = lambda s, e, j: F.coalesce(F.get(s, j)["x"] == e["x"], F.lit(False))
    # the sorted array is bound once, as the only element of an array
    repeats = F.get(
        F.transform(F.array(placed), lambda s: F.filter(s, lambda e, j: twin(s, e, j - 1) | twin(s, e, j + 1))), 0
    )
    at = F.array(F.sort_array(F.transform(repeats, lambda e: e["i"])))
    spans = F.get(
        F.transform(at, lambda p: F.zip_with(p, F.slice(p, 2, F.greatest(F.size(p), F.lit(1))), lambda a, b: F.coalesce(F.least(F.lit(5), b - a), F.lit(5)))), 0
    )
    total = F.aggregate(spans, F.lit(0), lambda a, b: a + b)
    return F.when(F.size(F.array_distinct(h)) == F.size(h), F.lit(0)).otherwise(total).cast("long")


def _vote(good: Column, bad: Column) -> Column:
    return F.when(bad, F.lit(0)).when(good, F.lit(1))


def rule_votes() -> dict[str, Column]:
    """Rules over the columns of :func:`measured`; shares are tested on integers."""
    n, chars = F.col("n_words"), F.col("word_chars")
    return {
        "length": _vote(n >= 50, n < 20),
        "symbols": _vote(F.col("n_symbols") * 200 <= chars, F.col("n_symbols") * 20 > chars),
        "repeats": _vote(F.col("n_repeat_words") * 50 <= n, F.col("n_repeat_words") * 20 > n),
        "lines": _vote(F.col("n_dup_lines") == 0, F.col("n_dup_lines") * 10 > F.col("n_lines")),
        "word_length": _vote((10 * chars >= n * 44) & (10 * chars <= n * 62), (10 * chars < n * 40) | (10 * chars > n * 70)),
        "capitals": _vote(F.col("n_upper") * 30 <= chars, F.col("n_upper") * 25 > chars),
        "variety": _vote(F.col("n_distinct") * 10 >= n * 6, F.col("n_distinct") * 20 < n * 11),
        "common_words": _vote(F.col("n_common") * 100 >= n * 14, F.col("n_common") * 100 < n * 8),
        "digits": _vote(F.col("n_digits") * 100 <= chars, F.col("n_digits") * 50 > chars),
        "single_marks": _vote(F.col("n_single") * 25 <= n, F.col("n_single") * 10 > n),
        "letters": _vote(F.col("n_lettered") * 20 >= n * 19, F.col("n_lettered") * 10 < n * 8),
        "closed_lines": _vote(F.col("n_closed") * 20 >= F.col("n_lines") * 19, F.col("n_closed") * 10 < F.col("n_lines") * 9),
    }


@dataclass
class RuleModel:
    """Share of good documents; per rule, how often its vote is right on good and on bad ones."""

    good: float
    right_good: list[float]
    right_bad: list[float]

    def posterior(self, votes: str) -> Column:
        """Probability of being good, from an array of votes; abstentions say nothing.

        The weights are one array constant, so that every round of the estimation
        runs the same generated code.
        """
        prior = math.log(self.good / (1 - self.good))
        weights = [(math.log(p / (1 - q)), math.log((1 - p) / q)) for p, q in zip(self.right_good, self.right_bad, strict=True)]
        table = F.array(*[F.array(F.lit(a), F.lit(b)) for a, b in weights])
        said = F.zip_with(F.col(votes), table, lambda v, w: F.when(v == 1, w[0]).when(v == 0, w[1]).otherwise(F.lit(0.0)))
        odds = F.aggregate(said, F.get(F.array(F.lit(prior)), F.lit(0)), lambda a, x: a + x)
        return F.lit(1.0) / (F.lit(1.0) + F.exp(-odds))


def estimate(patterns: DataFrame, n_rules: int) -> RuleModel:
    """Expectation-maximisation on (votes, n).  No row gives the start values.

    A round is one aggregate whose result has a row per rule and vote.
    """
    model = RuleModel(START_GOOD, [START_RIGHT_GOOD] * n_rules, [START_RIGHT_BAD] * n_rules)
    for _ in range(ROUNDS):
        weighed = patterns.select("votes", "n", model.posterior("votes").alias("p"))
        cast = weighed.select("n", "p", F.posexplode(F.concat("votes", F.array(F.lit(1).cast("tinyint")))).alias("rule", "vote"))
        sums = cast.where("vote is not null").groupBy("rule", "vote").agg(F.sum(F.col("n") * F.col("p")).alias("good"), F.sum("n").alias("n"))
        got = {(r["rule"], r["vote"]): (r["good"], r["n"] - r["good"]) for r in sums.collect()}
        if not got:
            return model
        good, bad = got[n_rules, 1]  # the appended vote counts every document
        share = lambda right, voted, start: (right + PRIOR_VOTES * start) / (voted + PRIOR_VOTES)
        new = RuleModel(share(good, good + bad, START_GOOD), [], [])
        for r in range(n_rules):
            (yes_good, yes_bad), (no_good, no_bad) = got.get((r, 1), (0.0, 0.0)), got.get((r, 0), (0.0, 0.0))
            new.right_good.append(share(yes_good, yes_good + no_good, START_RIGHT_GOOD))
            new.right_bad.append(share(no_bad, yes_bad + no_bad, START_RIGHT_BAD))
        was, now = [[m.good, *m.right_good, *m.right_bad] for m in (model, new)]
        model = new
        if max(abs(x - y) for x, y in zip(was, now, strict=True)) < SETTLED:
            break
    return model


def judged(docs: DataFrame, id_col: str = "doc_id", text_col: str = "text") -> DataFrame:
    """``id_col``, the measures, base_failed, quality_prob, all_passed and kept for each row.

    ``all_passed`` is what the demand that no rule votes against would keep.

    Null and empty texts have measures of 0 and fail.  Repeated rows are judged
    each.  Other columns are ignored.  An empty table gives an empty result.
    """
    base = measured(docs, id_col, text_col)
    votes = F.array(*[v.cast("tinyint") for v in rule_votes().values()])
    voted = materialize(base.withColumn("votes", votes), "rules-votes")
    n = F.col("n_words")
    failed = (n < MIN_WORDS) | (100 * F.col("n_repeat_words") > MAX_REPEAT_SHARE * n)
    patterns = materialize(voted.where(~failed).groupBy("votes").agg(F.count("*").alias("n")).coalesce(1), "rules-patterns")
    model = estimate(patterns, len(rule_votes()))
    out = voted.withColumn("base_failed", failed).withColumn("quality_prob", model.posterior("votes"))
    out = out.withColumn("all_passed", ~F.col("base_failed") & ~F.exists("votes", lambda v: F.coalesce(v == 0, F.lit(False))))
    return out.withColumn("kept", ~F.col("base_failed") & (F.col("quality_prob") >= KEEP_FROM)).withColumnRenamed("id", id_col)


def op3_quality_rules(spark: SparkSession, sf_dir: str) -> DataFrame:
    docs = spark.read.parquet(f"{sf_dir}/documents.parquet")
    return judged(docs).select(
        "doc_id", "n_words", "word_chars", "n_symbols", "n_dup_lines", "n_repeat_words", "base_failed", "quality_prob", "all_passed", "kept"
    )


def quality_base_measures(spark: SparkSession, sf_dir: str) -> DataFrame:
    """The measures and the base verdict alone, which SQL can state."""
    return op3_quality_rules(spark, sf_dir).select("doc_id", "n_words", "word_chars", "n_symbols", "n_dup_lines", "n_repeat_words", "base_failed")


BASE_SQL = r"""
WITH t AS (SELECT doc_id, coalesce(text, '') AS text, regexp_extract_all(coalesce(text, ''), '[^\x20\x09-\x0D]+') AS w,
                  list_filter(string_split(coalesce(text, ''), chr(10)), lambda l: regexp_matches(l, '[^\x20\x09-\x0D]')) AS ls FROM documents),
     win AS (SELECT doc_id, i, array_to_string(w[i:i + 4], ' ') AS g FROM (SELECT doc_id, w, unnest(range(1, len(w) - 3)) AS i FROM t WHERE len(w) >= 5)),
     twice AS (SELECT doc_id, i FROM win WINDOW k AS (PARTITION BY doc_id, g) QUALIFY count(*) OVER k > 1),
     cov AS (SELECT doc_id, count(DISTINCT i + k) AS n FROM twice, range(5) r(k) GROUP BY 1),
     m AS (SELECT t.doc_id, len(w) AS n_words, length(array_to_string(w, '')) AS word_chars, length(regexp_replace(text, '[^#*$%&|<>]', '', 'g')) AS n_symbols,
                  len(ls) - len(list_distinct(ls)) AS n_dup_lines, coalesce(cov.n, 0) AS n_repeat_words FROM t LEFT JOIN cov USING (doc_id))
SELECT *, n_words < 10 OR 100 * n_repeat_words > 20 * n_words AS base_failed FROM m
"""
