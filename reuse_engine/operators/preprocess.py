"""Normalization and the two-stage removal of exact duplicates.

Stage 1 groups by the hash of the runtime, stage 2 by the hash of its operand-
free tokens.  Both are hash aggregates with a map-side part, so the largest group
of copies costs a row for each task.  All later operators consume units.
"""

from __future__ import annotations

from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from reuse_engine.functions.dialects import DIALECTS, STAGES, normalized_columns
from reuse_engine.sources.artifacts import CORPORA

LATEST = (1 << 62)
KEYS = ["artifact_id", "corpus", "origin", "creator", "bundle_id", "deployed_us", "volume_milli"]


def strip_prefix(arts: DataFrame, dialect: str) -> DataFrame:
    """Adds ``body``; had_prefix is false where nothing was cut."""
    body = DIALECTS[dialect].strip_prefix(F.col("payload"))
    return arts.withColumn("body", body).withColumn("had_prefix", F.col("body") != F.col("payload"))


def strip_trailer(arts: DataFrame, dialect: str) -> DataFrame:
    """Adds ``body``; had_trailer is false where nothing was cut."""
    body = DIALECTS[dialect].strip_trailer(F.col("payload"))
    return arts.withColumn("body", body).withColumn("had_trailer", F.col("body") != F.col("payload"))


def normalize(arts: DataFrame, dialect: str, stages: tuple[str, ...] = STAGES, algo: str = "md5") -> DataFrame:
    """KEYS, raw_hash, runtime, runtime_hash, tok, token_hash, had_prefix, had_trailer."""
    hashed = {"md5": F.md5, "sha256": lambda c: F.sha2(c, 256), "xxhash64": lambda c: F.hex(F.xxhash64(c))}[algo]
    cols = normalized_columns(F.col("payload"), dialect, stages)
    with_runtime = arts.select(*KEYS, hashed(F.col("payload")).alias("raw_hash"), *[c.alias(n) for n, c in cols.items()])
    tok = DIALECTS[dialect].tokens(F.col("runtime"), "operands" in stages)
    return with_runtime.withColumn("tok", tok).withColumn("runtime_hash", hashed(F.col("runtime"))).withColumn("token_hash", hashed(F.col("tok")))


def corpus_normalized(arts: DataFrame, corpus: str, stages: tuple[str, ...] = STAGES) -> DataFrame:
    return normalize(arts, CORPORA[corpus], stages)


def dedupe(norm: DataFrame, by: str) -> DataFrame:
    """Groups of equal ``by`` (runtime_hash or token_hash) per corpus and origin."""
    return norm.groupBy("corpus", "origin", by).agg(
        F.count("*").alias("n_artifacts"),
        F.countDistinct("creator").alias("n_creators"),
        F.min_by("artifact_id", _age()).alias("first_artifact"),
    )


def _age():
    return F.struct(F.coalesce("deployed_us", F.lit(LATEST)), F.col("artifact_id"))


def units(norm: DataFrame) -> DataFrame:
    """One row per distinct token string of a corpus and origin, named by its earliest artifact."""
    first = F.min(F.struct(F.coalesce("deployed_us", F.lit(LATEST)).alias("us"), F.col("artifact_id").alias("id"), F.col("creator").alias("creator")))
    grouped = norm.groupBy("corpus", "origin", "token_hash").agg(
        first.alias("f"),
        F.count("*").alias("n_dup"),
        F.countDistinct("runtime_hash").alias("n_runtime"),
        F.countDistinct("creator").alias("n_creators"),
        F.min("tok").alias("tok"),
        F.min(F.length("runtime")).cast("bigint").alias("n_bytes"),
    )
    return grouped.select(
        "corpus", "origin", "token_hash", F.col("f.id").alias("unit_id"), "n_dup", "n_runtime", "n_creators",
        F.col("f.creator").alias("creator"), F.when(F.col("f.us") != LATEST, F.col("f.us")).alias("first_seen_us"), "tok", "n_bytes",
    )


def redeploys(norm: DataFrame) -> DataFrame:
    """Runtimes that were deployed with different raw payloads."""
    return norm.groupBy("runtime_hash").agg(F.countDistinct("raw_hash").alias("n_raw"), F.count("*").alias("n_artifacts")).where("n_raw > 1")
