"""Streaming variants as named queries, compared with the batch result where that is fixed."""

from __future__ import annotations

from pyspark.sql import functions as F

from reuse_engine import graph
from reuse_engine.operators import fingerprints, preprocess
from reuse_engine.plans import sqltext as S
from reuse_engine.plans.methods import fingers_of, pairs_of
from reuse_engine.plans.registry import query
from reuse_engine.sources.artifacts import artifacts
from reuse_engine.storage import materialize
from reuse_engine.streaming import streams

#: Windows that the final watermark has closed: their end is at most the last event less one day.
_CLOSED = "(SELECT max(epoch_us(ts)) - 86400000000 FROM events)"


def _closed(spark, d):
    return spark.read.parquet(f"{d}/events.parquet").agg(F.max(F.unix_micros(F.col("ts").cast("timestamp"))) - streams.DAY_US).first()[0]


@query("q_stream_tumbling", f"SELECT * FROM (SELECT epoch_us(date_trunc('day', ts)) AS day_us, CASE WHEN user_id % 2 = 0 THEN 'direct' ELSE 'factory' END AS origin, count(*) AS n_events, count(DISTINCT user_id) AS n_creators FROM events GROUP BY ALL) WHERE day_us + 86400000000 <= {_CLOSED}")
def _tumbling(spark, d):
    return streams.run_now(streams.tumbling(streams.event_stream(spark, d)), "tumbling").where(F.col("day_us") + streams.DAY_US <= _closed(spark, d))


@query("q_stream_sliding", f"SELECT * FROM (SELECT epoch_us(date_trunc('day', ts)) - k * 86400000000 AS start_us, count(*) AS n_events, count(*) FILTER (WHERE event_type = 'purchase') AS n_purchases FROM events, range(0, 7) r(k) GROUP BY 1) WHERE start_us + 7 * 86400000000 <= {_CLOSED}")
def _sliding(spark, d):
    return streams.run_now(streams.sliding(streams.event_stream(spark, d)), "sliding").where(F.col("start_us") + 7 * streams.DAY_US <= _closed(spark, d))


@query("q_stream_session", f"""SELECT user_id, min(us) AS start_us, count(*) AS n_events FROM (
  SELECT user_id, us, sum(fresh) OVER (PARTITION BY user_id ORDER BY us, event_id ROWS UNBOUNDED PRECEDING) AS burst FROM (
    SELECT user_id, event_id, epoch_us(ts) AS us, CASE WHEN epoch_us(ts) - lag(epoch_us(ts)) OVER (PARTITION BY user_id ORDER BY ts, event_id) < 21600000000 THEN 0 ELSE 1 END AS fresh FROM events))
  GROUP BY user_id, burst HAVING max(us) + 21600000000 <= {_CLOSED}""")
def _session(spark, d):
    """Bursts that end before the final watermark."""
    got = streams.run_now(streams.sessions(streams.event_stream(spark, d)), "session")
    return got.where(F.col("end_us") <= _closed(spark, d)).drop("end_us")


def _deployed(spark, d):
    """A stream of weekly scripts with fingerprints; every column is a built-in expression of the payload."""
    norm = preprocess.normalize(streams.artifact_stream(artifacts(spark, d, "scripts_week"), "scripts"), "script")
    units = norm.select("corpus", "origin", "token_hash", "artifact_id", F.col("artifact_id").alias("unit_id"), F.col("deployed_us").alias("us"), "tok", "creator",
                        F.lit(1).cast("bigint").alias("n_dup"), F.col("deployed_us").alias("first_seen_us"), F.length("runtime").cast("bigint").alias("n_bytes"))
    fps = fingerprints.fingers(units, "script").select("unit_id", "fp", "fp_len", "n_ops", "origin", "token_hash", F.col("first_seen_us").alias("us"))
    return fps.withColumnRenamed("unit_id", "artifact_id")


_WEEK = S.normalized(["scripts_week"])


@query("q_stream_dedupe", S.with_(_WEEK, "SELECT DISTINCT origin, token_hash FROM norm"))
def _dedupe(spark, d):
    return streams.run_now(streams.first_seen(_deployed(spark, d)), "dedupe")


@query("q_stream_static", S.with_(S.fingers(["scripts_week"]), """SELECT artifact_id, unit_id, (10000 * (m - dist)) // m AS score_bp FROM (
  SELECT n.artifact_id, y.unit_id, levenshtein(x.fp, y.fp) AS dist, greatest(x.fp_len, y.fp_len) AS m
  FROM norm n JOIN finger x ON x.origin = n.origin AND x.token_hash = n.token_hash JOIN finger y ON y.origin = x.origin AND 10 * least(x.n_ops, y.n_ops) >= 7 * greatest(x.n_ops, y.n_ops)
  WHERE x.fp_len > 0 AND y.fp_len > 0) WHERE 100 * (m - dist) >= 70 * m"""))
def _static(spark, d):
    return streams.neighbours_now(_deployed(spark, d), fingers_of(spark, d, ["scripts_week"]))


_REPORTS = """SELECT c.event_id AS deploy_id, p.event_id AS report_id FROM events c {how} JOIN events p ON c.user_id = p.user_id AND p.event_type = 'error'
  AND p.ts >= c.ts AND p.ts <= c.ts + INTERVAL 1 HOUR WHERE c.event_type = 'signup'"""


def _sides(spark, d):
    return [streams.event_stream(spark, d).where(F.col("event_type") == kind) for kind in ("signup", "error")]


@query("q_stream_interval", _REPORTS.format(how=""))
def _interval(spark, d):
    return streams.run_now(streams.reported(*_sides(spark, d)), "interval")


@query("q_stream_interval_outer", f"SELECT * FROM ({_REPORTS.format(how='LEFT')} AND epoch_us(c.ts) <= (SELECT min(us) FROM (SELECT max(epoch_us(ts)) - 3 * 3600000000 AS us FROM events WHERE event_type IN ('signup', 'error') GROUP BY event_type)))")
def _interval_outer(spark, d):
    """Deployments whose hour the watermark of both sides has passed, with or without a report."""
    got = streams.run_now(streams.reported(*_sides(spark, d), "left_outer"), "interval-outer")
    events = spark.read.parquet(f"{d}/events.parquet").withColumn("us", F.unix_micros(F.col("ts").cast("timestamp")))
    until = events.where("event_type in ('signup', 'error')").groupBy("event_type").agg(F.max("us").alias("us")).agg(F.min("us")).first()[0] - 3 * 3_600_000_000
    return got.join(events.where(F.col("us") <= until).select(F.col("event_id").alias("deploy_id")), "deploy_id", "left_semi")


@query("q_stream_stateful", S.with_(f"{S.pairs(['scripts_week'])},\n{S.components()}", f"""SELECT l AS cluster_id, min(coalesce(deployed_us, {S.LATEST})) AS first_us, first(artifact_id ORDER BY deployed_us, artifact_id) AS artifact_id
  FROM norm n JOIN unit u ON u.origin = n.origin AND u.token_hash = n.token_hash JOIN label ON v = u.unit_id GROUP BY 1"""))
def _stateful(spark, d):
    cl = graph.connected_components(pairs_of(spark, d, ["scripts_week"]), label="stream-clusters").toDF("unit_id", "cluster_id")
    labels = materialize(fingers_of(spark, d, ["scripts_week"]).join(cl, "unit_id").select("origin", "token_hash", "cluster_id"), "stream-labels")
    return streams.run_now(streams.cluster_originals(_deployed(spark, d), labels), "stateful", "update", ("cluster_id",))


@query("q_stream_late")
def _late(spark, d):
    return streams.late_rows(spark, d)


@query("s07_components_batch", S.with_(f"{S.pairs(['documents'])},\n{S.components()}", "SELECT v AS vertex, l AS component FROM label"))
def _components(spark, d):
    return streams.components_in_batches(pairs_of(spark, d, ["documents"]))
