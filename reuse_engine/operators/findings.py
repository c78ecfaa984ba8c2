"""Findings: seven kinds of detectors, inheritance through copies, pair behaviour."""

from __future__ import annotations

from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

from reuse_engine.storage import few_broadcast, materialize

#: Kind: pattern whose matches count. Fixed values.
PATTERNS = {
    "email": r"[A-Za-z0-9._-]+@[A-Za-z0-9.]+",
    "ipv4": r"[0-9]{1,3}(?:[.][0-9]{1,3}){3}",
    "phone": r"[+]1 [(][0-9]{3}[)] [0-9]{3}-[0-9]{4}",
    "secret": r"(?:token|key|secret|password) *[=:]",
}
#: Words of a passage by which it is looked up, and characters where it has too few words.
ANCHOR_WORDS, ANCHOR_CHARS = 3, 8


def _word_windows(words: Column, k: int) -> Column:
    """Distinct hashes of the windows of ``k`` words."""
    at = F.transform(F.sequence(F.lit(0), F.size(words) - k), lambda i: F.xxhash64(*[F.get(words, i + j) for j in range(k)]))
    return F.when(F.size(words) >= k, F.array_distinct(at)).otherwise(F.array().cast("array<bigint>"))


def passages_held(payloads: DataFrame, passages: DataFrame) -> DataFrame:
    """(unit_id, passage): passages, of any length, that stand in a payload as substrings.

    The words inside a passage, between its first and its last space, are words of
    every payload that holds it, so a window of them is looked up by equality; a
    passage with fewer inner words is looked up by characters, which costs a row per
    character and is done only if there is one.  Only ids and hashes are joined;
    payloads come back for the rows that met, and containment is tested on these.
    """
    given = passages.where(F.col("text") != "").select(F.col("text").alias("passage")).distinct()
    inner = F.filter(F.slice(F.split("passage", " "), 2, F.greatest(F.size(F.split("passage", " ")) - 2, F.lit(0))), lambda w: w != "")
    given = materialize(given.withColumn("inner", inner).withColumn("by_words", F.size("inner") >= ANCHOR_WORDS), "passages")
    heads = given.where("by_words").select("passage", F.get(_word_windows(F.col("inner"), ANCHOR_WORDS), F.lit(0)).alias("h"))
    words = payloads.select("unit_id", F.filter(F.split("payload", " "), lambda w: w != "").alias("w"))
    met = words.select("unit_id", F.explode_outer(_word_windows(F.col("w"), ANCHOR_WORDS)).alias("h")).join(few_broadcast(heads), "h").select("unit_id", "passage")
    few = given.where(~F.col("by_words"))
    if few.head(1):
        k = min(ANCHOR_CHARS, few.agg(F.min(F.length("passage"))).first()[0])
        starts = F.sequence(F.lit(1), F.length("payload") - k + 1)
        parts = F.when(F.length("payload") >= k, F.array_distinct(F.transform(starts, lambda i: F.xxhash64(F.substr(F.col("payload"), i, F.lit(k))))))
        by_chars = few.select("passage", F.xxhash64(F.substring("passage", 1, k)).alias("h"))
        met = met.unionByName(payloads.select("unit_id", F.explode_outer(parts).alias("h")).join(few_broadcast(by_chars), "h").select("unit_id", "passage"))
    met = materialize(met.distinct(), "passages-met")
    whole = payloads.join(few_broadcast(met.select("unit_id").distinct()), "unit_id", "left_semi")
    return met.join(whole, "unit_id").where(F.contains("payload", "passage")).select("unit_id", "passage")


def scan(payloads: DataFrame, labels: DataFrame, passages: DataFrame) -> DataFrame:
    """(unit_id, ftype, n) with n > 0.

    ``payloads``: unit_id, payload of each unit's representative.  ``labels``:
    unit_id, quality, toxic.  ``passages``: text; empty and null ones say nothing.
    """
    cols = {k: F.regexp_count("payload", F.lit(p)).cast("bigint") for k, p in PATTERNS.items()}
    wide = payloads.select("unit_id", *[c.alias(k) for k, c in cols.items()])
    kinds = ", ".join(f"'{k}', {k}" for k in PATTERNS)
    by_pattern = wide.selectExpr("unit_id", f"stack({len(PATTERNS)}, {kinds}) as (ftype, n)").where("n > 0")
    held = passages_held(payloads, passages).groupBy("unit_id").agg(F.count("*").alias("n")).select("unit_id", F.lit("contamination").alias("ftype"), "n")
    marked = labels.selectExpr("unit_id", "stack(2, 'toxic', int(toxic = 1), 'low_quality', int(quality = 0)) as (ftype, n)").where("n > 0")
    return by_pattern.unionByName(held).unionByName(marked.withColumn("n", F.col("n").cast("bigint")))


def finding_sets(found: DataFrame, count_mode: str = "per_type") -> DataFrame:
    """(unit_id, finds): sorted array of (ftype, n); ``total`` keeps the sum beside the kinds."""
    arrays = found.groupBy("unit_id").agg(F.sort_array(F.collect_list(F.struct("ftype", "n"))).alias("finds"))
    if count_mode == "per_type":
        return arrays
    total = F.aggregate("finds", F.lit(0).cast("bigint"), lambda a, f: a + f["n"])
    return arrays.select("unit_id", F.transform("finds", lambda f: F.struct(f["ftype"].alias("ftype"), total.alias("n"))).alias("finds"))


def _kinds(c: Column) -> Column:
    return F.transform(c, lambda f: f["ftype"])


def behaviour(a: Column, b: Column) -> Column:
    """neither, both_same, one, overlap or disjoint for two arrays of findings (null: none)."""
    none_a, none_b = a.isNull(), b.isNull()
    return (
        F.when(none_a & none_b, "neither").when(none_a | none_b, "one").when(a == b, "both_same")
        .when(F.arrays_overlap(_kinds(a), _kinds(b)), "overlap").otherwise("disjoint")
    )


def classified_pairs(pairs: DataFrame, units: DataFrame, found: DataFrame, count_mode: str = "per_type") -> DataFrame:
    """Pairs with behaviour class and whether both units have the same creator."""
    side = units.select("unit_id", "creator", "first_seen_us").join(finding_sets(found, count_mode), "unit_id", "left")

    def named(s: str) -> DataFrame:
        return side.select(F.col("unit_id").alias(s), F.col("creator").alias(f"creator_{s}"), F.col("first_seen_us").alias(f"seen_{s}"), F.col("finds").alias(f"finds_{s}"))

    both = pairs.select("a", "b").join(named("a"), "a").join(named("b"), "b")
    return both.withColumn("cls", behaviour(F.col("finds_a"), F.col("finds_b"))).withColumn("same_author", F.col("creator_a") == F.col("creator_b"))


def shared_creators(pairs: DataFrame, unit_creators: DataFrame) -> DataFrame:
    """Pairs with ``same_author``: some creator deployed instances of both units; ``unit_creators``: unit_id, creator."""
    own = unit_creators.distinct()
    x = own.select(F.col("unit_id").alias("a"), "creator")
    y = own.select(F.col("unit_id").alias("b"), "creator")
    both = pairs.select("a", "b").join(x, "a").join(y, ["b", "creator"]).select("a", "b").distinct().withColumn("hit", F.lit(True))
    return pairs.select("a", "b").join(both, ["a", "b"], "left").select("a", "b", F.coalesce("hit", F.lit(False)).alias("same_author"))


CLASSES = ("neither", "both_same", "one", "overlap", "disjoint")


def behaviour_table(classified: DataFrame) -> DataFrame:
    """Counts per class, for same and different authors and for both (null)."""
    counts = [F.count_if(F.col("cls") == c).alias(c) for c in CLASSES]
    return classified.rollup("same_author").agg(*counts)


def prevalence(units: DataFrame, found: DataFrame) -> DataFrame:
    """Vulnerable units and, through copies, artifacts, per origin."""
    bad = found.select("unit_id").distinct().withColumn("bad", F.lit(1))
    return units.join(bad, "unit_id", "left").groupBy("origin").agg(
        F.count("*").alias("n_units"), F.count("bad").alias("n_vuln_units"), F.sum("n_dup").cast("bigint").alias("n_artifacts"),
        F.coalesce(F.sum(F.when(F.col("bad") == 1, F.col("n_dup"))), F.lit(0)).cast("bigint").alias("n_vuln_artifacts"),
    )


def inherit(found: DataFrame, norm: DataFrame, units: DataFrame) -> DataFrame:
    """(artifact_id, ftype, n): every copy has the findings of its unit."""
    named = norm.select("artifact_id", "corpus", "origin", "token_hash").join(units.select("corpus", "origin", "token_hash", "unit_id"), ["corpus", "origin", "token_hash"])
    return named.join(found, "unit_id").select("artifact_id", "ftype", "n")


def case_cluster(cl: DataFrame, units: DataFrame, found: DataFrame) -> DataFrame:
    """The largest cluster whose earliest unit has a finding: share of members with that kind."""
    aged = cl.join(units.select("unit_id", "first_seen_us"), "unit_id")
    first = aged.groupBy("cluster_id").agg(
        F.count("*").alias("n_units"), F.min(F.struct(F.coalesce("first_seen_us", F.lit(1 << 62)).alias("us"), "unit_id"))["unit_id"].alias("unit_id")
    )
    kind = found.groupBy("unit_id").agg(F.min("ftype").alias("ftype"))
    chosen = first.join(kind, "unit_id").orderBy(F.desc("n_units"), "cluster_id").limit(1).select("cluster_id", "n_units", "ftype")
    holders = cl.join(F.broadcast(chosen), "cluster_id").join(found.select("unit_id", "ftype"), ["unit_id", "ftype"])
    counted = holders.groupBy("cluster_id", "ftype").agg(F.count("*").alias("n_with"), F.max("n_units").alias("n_units"))
    return counted.select("cluster_id", "ftype", "n_units", "n_with", F.expr("(10000 * n_with) div n_units").alias("share_bp"))


def patch_direction(classified: DataFrame) -> DataFrame:
    """Of one-sided pairs: is the earlier or the later unit the one with findings?"""
    one = classified.where("cls = 'one' and seen_a is not null and seen_b is not null and seen_a <> seen_b")
    early_bad = F.when(F.col("seen_a") < F.col("seen_b"), F.col("finds_a").isNotNull()).otherwise(F.col("finds_b").isNotNull())
    return one.groupBy(F.when(early_bad, "fixed_later").otherwise("introduced_later").alias("direction")).agg(F.count("*").alias("n_pairs"))

