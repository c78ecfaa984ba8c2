"""Piecewise fingerprints of units: block cutting and the alternatives to it."""

from __future__ import annotations

from collections.abc import Callable

from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

from reuse_engine.functions.dialects import DIALECTS, STAGES, normalized_columns
from reuse_engine.functions.symbols import fingerprint as symbols_of
from reuse_engine.functions.symbols import piece_hash, symbol

FEATURES = ("n_ops", "n_pieces", "n_distinct_ops", "n_terminators", "n_operand_bytes", "n_bytes")
RANDOM_PERIOD, SEED = 8, 42


def token_array(dialect: str) -> Column:
    d = DIALECTS[dialect]
    whole = F.when(F.col("tok") == "", F.array().cast("array<string>"))
    return whole.otherwise(F.split("tok", d.gap if d.gap else ""))


def _at_boundaries(tokens: Column, ends: Callable[[Column], Column], gap: str) -> Column:
    """Pieces of a token array: ``ends(i)`` says whether token i (from 0) ends one."""
    marked = F.array_join(F.transform(tokens, lambda t, i: F.concat(t, F.when(ends(i), F.lit("|")).otherwise(F.lit(gap)))), "")
    return F.filter(F.transform(F.split(marked, r"\|"), lambda p: F.trim(p)), lambda p: p != "")


def pieces(units: DataFrame, dialect: str, method: str = "block", step: int = 7, window: int = 7, modulus: int = 16) -> DataFrame:
    """Adds ``pieces`` by a cutting method: block, fixed, random or rolling."""
    if method == "block":
        return units.withColumn("pieces", DIALECTS[dialect].pieces(F.col("tok")))
    gap = DIALECTS[dialect].gap
    if method == "fixed":
        ends = lambda s, i: (i + 1) % step == 0
    elif method == "random":
        draw = lambda i: F.md5(F.concat(F.col("unit_id"), F.lit(":"), i.cast("string"), F.lit(f":{SEED}")))
        ends = lambda s, i: F.conv(F.substring(draw(i), 1, 8), 16, 10).cast("bigint") % RANDOM_PERIOD == 0
    elif method == "rolling":
        total = lambda h, i: F.aggregate(F.slice(h, F.greatest(i - window + 2, F.lit(1)), F.least(i + 1, F.lit(window))), F.lit(0).cast("bigint"), lambda a, x: a + x)
        ends = lambda s, i: total(s["h"], i) % modulus == modulus - 1
    else:
        raise ValueError(f"unknown method {method}")
    # tokens and hashes are bound once, as the only element of an array
    hashes = F.transform(token_array(dialect), lambda t: F.crc32(t)) if method == "rolling" else F.lit(None).cast("array<bigint>")
    bound = F.array(F.struct(token_array(dialect).alias("t"), hashes.alias("h")))
    return units.withColumn("pieces", F.get(F.transform(bound, lambda s: _at_boundaries(s["t"], lambda i: ends(s, i), gap)), 0))


def tokens_of(rows: DataFrame, dialect: str, stages: tuple[str, ...] = STAGES) -> DataFrame:
    """(artifact_id, tok, token_hash) of payloads."""
    runtime = rows.select("artifact_id", normalized_columns(F.col("payload"), dialect, stages)["runtime"].alias("runtime"))
    tok = runtime.select("artifact_id", DIALECTS[dialect].tokens(F.col("runtime"), "operands" in stages).alias("tok"))
    return tok.withColumn("token_hash", F.md5("tok"))


#: Columns of :func:`prints` that stand for a text.
PRINTED = ("fp", "n_pieces", "n_ops", "n_distinct_ops", "n_terminators", "tok_chars")
LATEST = 1 << 62


def prints(rows: DataFrame, dialect: str, stages: tuple[str, ...] = STAGES, method: str = "block", algo: str = "md5", digest_chars: int = 8, **options: int) -> DataFrame:
    """``rows`` (artifact_id, payload and more) with token_hash, n_bytes and :data:`PRINTED` of each payload in its place."""
    runtime = rows.withColumn("__runtime", normalized_columns(F.col("payload"), dialect, stages)["runtime"]).drop("payload")
    tok = runtime.withColumn("tok", DIALECTS[dialect].tokens(F.col("__runtime"), "operands" in stages)).withColumn("unit_id", F.col("artifact_id"))
    cut = pieces(tok, dialect, method, **options)
    return cut.select(
        *[c for c in rows.columns if c != "payload"],
        F.md5("tok").alias("token_hash"),
        F.length("__runtime").cast("bigint").alias("n_bytes"),
        symbols_of(F.col("pieces"), algo, digest_chars).alias("fp"),
        F.size("pieces").alias("n_pieces"),
        DIALECTS[dialect].count(F.col("tok")).cast("bigint").alias("n_ops"),
        F.size(F.array_distinct(token_array(dialect))).cast("bigint").alias("n_distinct_ops"),
        F.regexp_count("tok", F.lit(DIALECTS[dialect].ender)).cast("bigint").alias("n_terminators"),
        F.length("tok").alias("tok_chars"),
    )


def printed_units(printed: DataFrame) -> DataFrame:
    """As :func:`fingers` of the units, without tok, from artifacts with :func:`prints`: no text is dealt out.

    A unit is named by its earliest artifact and has that one's fingerprint.
    """
    first = F.min(F.struct(F.coalesce("deployed_us", F.lit(LATEST)).alias("us"), F.col("artifact_id").alias("id"), "creator", *PRINTED))
    grouped = printed.groupBy("corpus", "origin", "token_hash").agg(first.alias("f"), F.count("*").alias("n_dup"), F.min("n_bytes").alias("n_bytes"))
    return grouped.select(
        "corpus", "origin", F.col("f.id").alias("unit_id"), "token_hash", "n_dup", F.col("f.creator").alias("creator"),
        F.when(F.col("f.us") != LATEST, F.col("f.us")).alias("first_seen_us"), F.col("f.fp").alias("fp"), F.col("f.n_pieces").alias("fp_len"),
        F.col("f.n_ops").alias("n_ops"), F.col("f.n_pieces").cast("bigint").alias("n_pieces"), F.col("f.n_distinct_ops").alias("n_distinct_ops"),
        F.col("f.n_terminators").alias("n_terminators"), F.greatest(F.col("n_bytes") - F.col("f.tok_chars"), F.lit(0)).cast("bigint").alias("n_operand_bytes"), "n_bytes",
    )


def fingers(units: DataFrame, dialect: str, method: str = "block", algo: str = "md5", digest_chars: int = 8, **options: int) -> DataFrame:
    """Units with fp, fp_len and the meta features; units without a piece have fp_len 0."""
    cut = pieces(units, dialect, method, **options)
    tokens = token_array(dialect)
    return cut.select(
        "corpus", "origin", "unit_id", "token_hash", "n_dup", "creator", "first_seen_us",
        symbols_of(F.col("pieces"), algo, digest_chars).alias("fp"),
        F.size("pieces").alias("fp_len"),
        DIALECTS[dialect].count(F.col("tok")).cast("bigint").alias("n_ops"),
        F.size("pieces").cast("bigint").alias("n_pieces"),
        F.size(F.array_distinct(tokens)).cast("bigint").alias("n_distinct_ops"),
        F.regexp_count("tok", F.lit(DIALECTS[dialect].ender)).cast("bigint").alias("n_terminators"),
        F.greatest(F.col("n_bytes") - F.length("tok"), F.lit(0)).cast("bigint").alias("n_operand_bytes"),
        "n_bytes",
        "tok",
    )


def collision_stats(units: DataFrame, dialect: str) -> DataFrame:
    """Per symbol: distinct pieces that map to it; more than one is a collision."""
    found = pieces(units, dialect).select(F.explode_outer("pieces").alias("piece")).where("piece is not null").distinct()
    return found.groupBy(symbol(piece_hash(F.col("piece"))).alias("symbol")).agg(F.count("*").alias("n_pieces"))


def collision_rate(stats: DataFrame) -> DataFrame:
    """Share of pairs of distinct pieces that map to one symbol, beside the share that an even spread gives (1/64)."""
    sums = stats.agg(F.sum("n_pieces").alias("n_pieces"), F.count("*").alias("n_symbols"), F.sum(F.expr("n_pieces * (n_pieces - 1) div 2")).alias("n_colliding"))
    rate = F.expr("(10000 * n_colliding) div greatest(n_pieces * (n_pieces - 1) div 2, 1)")
    return sums.withColumn("rate_bp", rate).withColumn("expected_bp", F.lit(10_000 // 64).cast("bigint"))


def compression(fps: DataFrame) -> DataFrame:
    """Fingerprint symbols for each ten thousand characters of code, per corpus and origin."""
    total = fps.groupBy("corpus", "origin").agg(
        F.count("*").alias("n_units"), F.sum("fp_len").cast("bigint").alias("symbols"), F.sum("n_bytes").cast("bigint").alias("bytes")
    )
    return total.withColumn("ratio_bp", F.expr("(10000 * symbols) div bytes"))


def symbol_diff(fp_a: Column, fp_b: Column) -> Column:
    """Positions at which two fingerprints differ; the shorter one is padded."""
    both = F.zip_with(F.split(fp_a, ""), F.split(fp_b, ""), lambda x, y: (~x.eqNullSafe(y)).cast("int"))
    return F.aggregate(both, F.lit(0), lambda a, x: a + x)
