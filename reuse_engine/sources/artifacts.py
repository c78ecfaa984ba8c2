"""The given tables as artifacts: one schema for every corpus.

artifact_id, corpus, origin, creator, bundle_id, deployed_us, payload,
volume_milli.  Times are microseconds since 1970 and volumes are thousandths, so
that no result depends on a session's time zone or on floating point.
"""

from __future__ import annotations

from collections.abc import Callable

from pyspark.sql import Column, DataFrame, SparkSession
from pyspark.sql import functions as F

from reuse_engine.functions.dialects import DEPLOY_MARKER, TRAILER_END, TRAILER_HEAD
from reuse_engine.storage import spread, table

COLUMNS = ["artifact_id", "corpus", "origin", "creator", "bundle_id", "deployed_us", "payload", "volume_milli"]

#: corpus: dialect
CORPORA = {
    "documents": "prose", "pages": "markup", "scripts": "script", "scripts_week": "script", "vm": "vmhex",
    "conversations": "prose", "rows": "rowseq", "vectors": "vector",
}
BUNDLE_DOCS = 80
#: Fixed values of the program compiler: code of a deploy, and a program per event type.
CREATION = "60015b"
OPCODES = {"view": "5b6001", "click": "6002600301", "signup": "61ffee35", "purchase": "6010", "error": "600080"}
ENDS = {"purchase": "57", "error": "fd"}


def micros(ts: str) -> Column:
    """Microseconds since 1970 of a zone-free timestamp."""
    return F.expr(f"timestampdiff(MICROSECOND, timestamp_ntz'1970-01-01 00:00:00', cast({ts} as timestamp_ntz))")


def _milli(c: Column) -> Column:
    return F.round(c * 1000).cast("bigint")


def host(url: Column) -> Column:
    return F.regexp_extract(url, "^https?://([^/?#]+)", 1)


def _documents(spark: SparkSession, d: str, derive: Callable[[DataFrame], DataFrame] = lambda rows: rows) -> DataFrame:
    given = spread(table(spark, d, "documents").select("doc_id", "text", "lang", "source"))
    docs = derive(given.select("doc_id", "lang", "source", F.col("doc_id").cast("string").alias("artifact_id"), F.coalesce("text", F.lit("")).alias("payload")))
    made = [c for c in docs.columns if c not in ("doc_id", "lang", "source", "artifact_id")]
    when = table(spark, d, "events").select(F.col("event_id").alias("doc_id"), micros("ts").alias("deployed_us"))
    volume = table(spark, d, "orders").select(F.col("o_orderkey").alias("doc_id"), _milli(F.col("o_totalprice")).alias("volume_milli"))
    rows = docs.join(when, "doc_id", "left").join(volume, "doc_id", "left")
    return rows.select(
        "artifact_id", F.lit("documents").alias("corpus"),
        F.when(F.col("lang") == "en", "direct").otherwise("factory").alias("origin"), F.col("source").alias("creator"),
        F.concat("source", F.lit("/"), F.floor(F.col("doc_id") / BUNDLE_DOCS).cast("string")).alias("bundle_id"),
        "deployed_us", *made, "volume_milli",
    )


def _pages(spark: SparkSession, d: str, derive: Callable[[DataFrame], DataFrame] = lambda rows: rows) -> DataFrame:
    given = spread(table(spark, d, "pages"))
    pages = derive(given.select("page_id", "url", F.col("page_id").cast("string").alias("artifact_id"), F.coalesce("html", F.lit("")).alias("payload")))
    made = [c for c in pages.columns if c not in ("page_id", "url", "artifact_id")]
    when = table(spark, d, "events").select(F.col("event_id").alias("page_id"), micros("ts").alias("deployed_us"), _milli(F.col("value")).alias("volume_milli"))
    return pages.join(when, "page_id", "left").select(
        "artifact_id", F.lit("pages").alias("corpus"), F.lit("factory").alias("origin"),
        host(F.col("url")).alias("creator"), host(F.col("url")).alias("bundle_id"), "deployed_us",
        *made, "volume_milli",
    )


def _event_steps(spark: SparkSession, d: str, period: str) -> DataFrame:
    """One row per user and period, its events in order as structs."""
    events = spread(table(spark, d, "events"))
    step = F.struct(micros("ts").alias("us"), "event_id", F.col("event_type").alias("kind"), F.col("value").alias("value"))
    return events.groupBy("user_id", micros_of_trunc(period).alias("period_us")).agg(
        F.sort_array(F.collect_list(step)).alias("steps"), F.min(micros("ts")).alias("deployed_us"), F.sum(_milli(F.col("value"))).alias("volume_milli")
    )


def micros_of_trunc(period: str) -> Column:
    """Start of the day, or of the seven days counted from 1970, as microseconds."""
    span = {"day": 86_400_000_000, "week": 7 * 86_400_000_000}[period]
    return micros("ts") - micros("ts") % span


def _scripts(spark: SparkSession, d: str, corpus: str) -> DataFrame:
    rows = _event_steps(spark, d, "week" if corpus == "scripts_week" else "day")
    payload = F.array_join(F.transform("steps", lambda s: F.concat(F.substring(s["kind"], 1, 1), _milli(s["value"]).cast("string"))), " ")
    user = F.col("user_id").cast("string")
    return rows.select(
        F.concat(user, F.lit("@"), F.expr("period_us div 86400000000").cast("string")).alias("artifact_id"), F.lit(corpus).alias("corpus"),
        _by_parity().alias("origin"), user.alias("creator"), user.alias("bundle_id"), "deployed_us", payload.alias("payload"), "volume_milli",
    )


def _by_parity() -> Column:
    return F.when(F.col("user_id") % 2 == 0, "direct").otherwise("factory")


def _vm(spark: SparkSession, d: str) -> DataFrame:
    """Programs compiled from user-day scripts: creation code, runtime, and a trailer that hashes the artifact."""
    rows = _event_steps(spark, d, "day")
    user = F.col("user_id").cast("string")
    name = F.concat(user, F.lit("@"), F.expr("period_us div 86400000000").cast("string"))

    def code(s: Column) -> Column:
        out = None
        for kind, body in OPCODES.items():
            operand = F.lpad(F.lower(F.hex(F.abs(_milli(s["value"])) % 256)), 2, "0")
            text = F.concat(F.lit("60"), operand, F.lit(body + ENDS.get(kind, "")))
            out = F.when(s["kind"] == kind, text) if out is None else out.when(s["kind"] == kind, text)
        return out.otherwise(F.lit("00"))

    runtime = F.array_join(F.transform("steps", code), "")
    digest = F.concat(F.md5(name), F.md5(F.concat(name, F.lit("#"))))
    payload = F.concat(F.lit(CREATION + DEPLOY_MARKER), runtime, F.lit(TRAILER_HEAD + "20"), digest, F.lit(TRAILER_END))
    return rows.select(
        name.alias("artifact_id"), F.lit("vm").alias("corpus"), _by_parity().alias("origin"), user.alias("creator"), user.alias("bundle_id"),
        "deployed_us", payload.alias("payload"), "volume_milli",
    )


def _conversations(spark: SparkSession, d: str) -> DataFrame:
    rows = spread(table(spark, d, "conversations"))
    return rows.select(
        F.concat(F.col("conv_id").cast("string"), F.lit("/"), F.col("turn").cast("string")).alias("artifact_id"), F.lit("conversations").alias("corpus"),
        F.when(F.col("role") == "assistant", "factory").otherwise("direct").alias("origin"), F.col("role").alias("creator"),
        F.col("conv_id").cast("string").alias("bundle_id"), F.lit(None).cast("bigint").alias("deployed_us"),
        F.coalesce("text", F.lit("")).alias("payload"), F.lit(None).cast("bigint").alias("volume_milli"),
    )


def _rows(spark: SparkSession, d: str) -> DataFrame:
    items = spread(table(spark, d, "lineitem"))
    orders = table(spark, d, "orders").select(F.col("o_orderkey").alias("l_orderkey"), F.col("o_custkey").cast("string").alias("creator"), micros("o_orderdate").alias("deployed_us"))
    quantity = F.col("l_quantity").cast("bigint")
    token = F.concat("l_returnflag", "l_linestatus", F.lit(":"), quantity.cast("string"))
    step = F.struct("l_linenumber", "l_returnflag", "l_linestatus", quantity.alias("q"), token.alias("token"))
    seqs = items.groupBy("l_orderkey").agg(
        F.sort_array(F.collect_list(step)).alias("steps"), F.sum(_milli(F.col("l_extendedprice"))).alias("volume_milli")
    )
    return seqs.join(orders, "l_orderkey", "left").select(
        F.col("l_orderkey").cast("string").alias("artifact_id"), F.lit("rows").alias("corpus"), F.lit("direct").alias("origin"), "creator",
        F.col("creator").alias("bundle_id"), "deployed_us", F.array_join(F.transform("steps", lambda s: s["token"]), " ").alias("payload"), "volume_milli",
    )


def _vectors(spark: SparkSession, d: str) -> DataFrame:
    rows = spread(table(spark, d, "embeddings"))
    bits = F.transform("embedding", lambda v: F.when(v > 0, "1").otherwise("0"))
    groups = F.transform(F.sequence(F.lit(0), F.lit(60), F.lit(6)), lambda i: F.array_join(F.slice(bits, i + 1, 6), ""))
    label = F.col("label").cast("string")
    return rows.select(
        F.col("vec_id").cast("string").alias("artifact_id"), F.lit("vectors").alias("corpus"), F.lit("direct").alias("origin"), label.alias("creator"),
        label.alias("bundle_id"), F.lit(None).cast("bigint").alias("deployed_us"), F.array_join(groups, " ").alias("payload"),
        F.lit(None).cast("bigint").alias("volume_milli"),
    )


def artifacts(spark: SparkSession, sf_dir: str, corpus: str, derive: Callable[[DataFrame], DataFrame] | None = None) -> DataFrame:
    """Artifacts of a corpus; see :data:`CORPORA`.

    ``derive`` replaces the column payload of given rows (artifact_id, payload and more)
    by others.  Texts of given tables are replaced before times and volumes are joined, so
    that what is derived is dealt out and not the texts.
    """
    joined = {"documents": _documents, "pages": _pages}
    if corpus in joined:
        return joined[corpus](spark, sf_dir, derive) if derive else joined[corpus](spark, sf_dir)
    made = {"vm": _vm, "conversations": _conversations, "rows": _rows, "vectors": _vectors}
    rows = made[corpus](spark, sf_dir) if corpus in made else _scripts(spark, sf_dir, corpus)
    return derive(rows) if derive else rows


def payloads(spark: SparkSession, sf_dir: str, corpus: str) -> DataFrame:
    """(artifact_id, payload) of a corpus; nothing is joined to the texts of given tables."""
    given = {"documents": ("doc_id", "text"), "pages": ("page_id", "html")}
    if corpus not in given:
        return artifacts(spark, sf_dir, corpus).select("artifact_id", "payload")
    name, text = given[corpus]
    return spread(table(spark, sf_dir, corpus).select(F.col(name).cast("string").alias("artifact_id"), F.coalesce(text, F.lit("")).alias("payload")))
