"""Structured Streaming variants: deployments arrive as ``events`` rows.

Every stream runs with the available-now trigger into a table of the shared
folder, and is read back as a batch.  Event times are cast from the zone-free
type first, which watermarks refuse.  A closing row far in the future moves the
watermark past all real windows, so appended results are complete.
"""

from __future__ import annotations

from collections.abc import Iterator

import pandas as pd
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F
from pyspark.sql.streaming.state import GroupState, GroupStateTimeout

from reuse_engine.functions.symbols import score_bp
from reuse_engine.graph import connected_components
from reuse_engine.operators import pairing
from reuse_engine.operators.chunks import chunk_pairs
from reuse_engine.storage import discard, materialize, new_path

DAY_US = 86_400_000_000


def event_stream(spark: SparkSession, sf_dir: str) -> DataFrame:
    """The events table as a file stream; ``us`` is the event time in microseconds."""
    batch = spark.read.parquet(f"{sf_dir}/events.parquet")
    rows = spark.readStream.schema(batch.schema).parquet(f"{sf_dir}/events.parq[u]et")  # a pattern, so that one file is a source too
    return rows.withColumn("ts", F.col("ts").cast("timestamp")).withColumn("us", F.unix_micros("ts"))


def run_now(stream: DataFrame, label: str, mode: str = "append", keys: tuple[str, ...] = ()) -> DataFrame:
    """Run to the end of what is there; returns what was written.

    In update mode every batch writes the rows of the keys that it touched, and the
    last row of each key counts, whatever the number of batches.
    """
    spark, path = stream.sparkSession, new_path(stream.sparkSession, f"stream-{label}")
    schema = stream.schema
    options = stream.writeStream.trigger(availableNow=True).option("checkpointLocation", new_path(spark, f"stream-{label}-state"))
    if mode == "append":
        options.format("parquet").option("path", path).start().awaitTermination()
        return spark.read.schema(schema).parquet(path)
    if not keys:
        raise ValueError("update mode needs the keys of a row")

    def save(rows: DataFrame, batch_id: int) -> None:
        rows.write.mode("overwrite").parquet(f"{path}/batch={batch_id}")

    options.outputMode(mode).foreachBatch(save).start().awaitTermination()
    others = [c for c in schema.names if c not in keys]
    rows = spark.read.schema(schema.add("batch", "long")).parquet(path)
    last = rows.groupBy(*keys).agg(F.max_by(F.struct(*others), "batch").alias("v"))
    return last.select(*[c if c in keys else F.col(f"v.{c}").alias(c) for c in schema.names if c != "batch"])


def artifact_stream(arts: DataFrame, label: str, parts: int = 4) -> DataFrame:
    """Deployments as a file stream: artifacts written to the shared folder in files, read a few at a time."""
    spark, path = arts.sparkSession, new_path(arts.sparkSession, f"stream-{label}-input")
    rows = arts.withColumn("deployed", F.timestamp_micros(F.coalesce("deployed_us", F.lit(0))))
    rows.repartition(parts, "artifact_id").write.parquet(path)
    return spark.readStream.schema(rows.schema).option("maxFilesPerTrigger", max(1, parts // 2)).parquet(path)


def tumbling(stream: DataFrame) -> DataFrame:
    """Events and distinct creators per origin and day.

    A day's creators are counted by two windowed aggregates in a row: one row per
    creator first, so that no state holds a set of creators.
    """
    day = F.window("ts", "1 day")
    origin = F.when(F.col("user_id") % 2 == 0, "direct").otherwise("factory")
    own = stream.withWatermark("ts", "1 day").groupBy(day.alias("w"), origin.alias("origin"), "user_id").agg(F.count("*").alias("n"))
    both = own.groupBy(F.window(F.window_time("w"), "1 day").alias("d"), "origin").agg(F.sum("n").alias("n_events"), F.count("*").alias("n_creators"))
    return both.select(F.unix_micros("d.start").alias("day_us"), "origin", "n_events", "n_creators")


def sliding(stream: DataFrame) -> DataFrame:
    week = F.window("ts", "7 days", "1 day")
    return stream.withWatermark("ts", "1 day").groupBy(week.alias("w")).agg(F.count("*").alias("n_events"), F.count_if(F.col("event_type") == "purchase").alias("n_purchases")).select(
        F.unix_micros("w.start").alias("start_us"), "n_events", "n_purchases"
    )


def sessions(stream: DataFrame) -> DataFrame:
    """Bursts of one creator with gaps under six hours."""
    burst = F.session_window("ts", "6 hours")
    return stream.withWatermark("ts", "1 day").groupBy(burst.alias("w"), "user_id").agg(F.count("*").alias("n_events")).select(
        "user_id", F.unix_micros("w.start").alias("start_us"), F.unix_micros("w.end").alias("end_us"), "n_events"
    )


def first_seen(units: DataFrame) -> DataFrame:
    """(origin, token_hash) when it is first deployed; the state is a hash per unit, as many as the stored units."""
    return units.select("origin", "token_hash").dropDuplicates(["origin", "token_hash"])


def known_neighbours(units: DataFrame, stored: DataFrame, threshold: int = 70) -> DataFrame:
    """(artifact_id, unit_id, score_bp): a batch of deployments against the stored fingerprints, by the chunk plan.

    ``units``: corpus, origin, artifact_id and fp, fp_len, n_ops of each deployment.
    Distinct fingerprints of both sides meet once, however often they were deployed.
    """
    new = units.where("fp_len > 0").select("origin", "artifact_id", "fp", "fp_len", F.col("n_ops").alias("n_a"))
    old = stored.where("fp_len > 0").select("origin", "unit_id", "fp", "fp_len", F.col("n_ops").alias("n_b"))
    sides = [side.select("origin", "fp", "fp_len", F.lit(not is_new).alias("old"), F.lit(is_new).alias("new")) for side, is_new in ((old, False), (new, True))]
    kinds = sides[0].unionByName(sides[1]).groupBy("origin", "fp", "fp_len").agg(F.max("old").alias("old"), F.max("new").alias("new"))
    met = chunk_pairs(kinds.select(F.lit("").alias("corpus"), "*", F.col("fp").alias("unit_id")), threshold, lambda n: pairing.length_bucket(n, threshold), sided=True)
    met = met.select("origin", F.col("a").alias("x"), F.col("b").alias("y"), "dist")
    same = kinds.where("old and new").select("origin", F.col("fp").alias("x"), F.col("fp").alias("y"), F.lit(0).alias("dist"))
    links = met.unionByName(met.select("origin", F.col("y").alias("x"), F.col("x").alias("y"), "dist")).unionByName(same)
    near = links.join(new.select("origin", F.col("fp").alias("x"), "artifact_id", "n_a", F.col("fp_len").alias("la")), ["origin", "x"])
    near = near.join(old.select("origin", F.col("fp").alias("y"), "unit_id", "n_b", F.col("fp_len").alias("lb")), ["origin", "y"])
    near = near.where("10 * least(n_a, n_b) >= 7 * greatest(n_a, n_b)").withColumn("m", F.greatest("la", "lb"))
    return near.select("artifact_id", "unit_id", score_bp(F.col("dist").cast("bigint"), F.col("m").cast("bigint")).alias("score_bp"))


def neighbours_now(units: DataFrame, stored: DataFrame) -> DataFrame:
    """Run :func:`known_neighbours` on every batch of a stream to the end of what is there."""
    spark, path = units.sparkSession, new_path(units.sparkSession, "stream-static")

    def save(rows: DataFrame, batch_id: int) -> None:
        kept = materialize(rows, "stream-static-batch")
        known_neighbours(kept, stored).write.mode("overwrite").parquet(f"{path}/batch={batch_id}")
        discard(kept)

    run = units.select("origin", "artifact_id", "fp", "fp_len", "n_ops").writeStream.trigger(availableNow=True)
    run.option("checkpointLocation", new_path(spark, "stream-static-state")).foreachBatch(save).start().awaitTermination()
    return spark.read.schema("artifact_id string, unit_id string, score_bp long").parquet(path).select("artifact_id", "unit_id", "score_bp")


def reported(deployments: DataFrame, reports: DataFrame, how: str = "inner") -> DataFrame:
    """(deploy_id, report_id): reports of a finding within an hour after a deployment of the same creator.

    Both sides have (user_id, event_id, ts).  A left outer join gives a deployment
    without a report once the watermark has passed its hour.
    """
    left = deployments.select(F.col("user_id").alias("u"), F.col("ts").alias("t0"), F.col("event_id").alias("deploy_id")).withWatermark("t0", "1 hour")
    right = reports.select("user_id", F.col("ts").alias("t1"), F.col("event_id").alias("report_id")).withWatermark("t1", "1 hour")
    near = F.expr("u = user_id and t1 >= t0 and t1 <= t0 + interval 1 hour")
    return left.join(right, near, how).select("deploy_id", "report_id")


def _earliest(key: tuple, batches: Iterator[pd.DataFrame], state: GroupState) -> Iterator[pd.DataFrame]:
    best = state.get if state.exists else (1 << 62, "")
    for pdf in batches:
        i = pdf.sort_values(["us", "artifact_id"]).iloc[0]
        best = min(best, (int(i["us"]), str(i["artifact_id"])))
    state.update(best)
    yield pd.DataFrame({"cluster_id": [key[0]], "first_us": [best[0]], "artifact_id": [best[1]]})


def cluster_originals(units: DataFrame, labels: DataFrame) -> DataFrame:
    """Earliest deployment of each cluster; one that arrives late may revise it, so updates are emitted.

    ``units``: origin, token_hash, artifact_id, us; ``labels``: origin, token_hash, cluster_id.
    """
    rows = units.join(labels, ["origin", "token_hash"]).select("cluster_id", "us", "artifact_id").groupBy("cluster_id")
    return rows.applyInPandasWithState(_earliest, "cluster_id string, first_us long, artifact_id string", "us long, artifact_id string", "update", GroupStateTimeout.NoTimeout)


def late_rows(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Rows that a one-day watermark drops when a second file repeats the oldest events after the newest."""
    events = spark.read.parquet(f"{sf_dir}/events.parquet").select("event_id", F.col("ts").cast("timestamp").alias("ts"))
    path = new_path(spark, "stream-late-input")
    events.write.parquet(path)
    source = spark.readStream.schema(events.schema).parquet(path)
    counts = source.withWatermark("ts", "1 day").groupBy(F.window("ts", "1 day")).count()
    out = new_path(spark, "stream-late-state")
    run = counts.writeStream.format("noop").trigger(availableNow=True).option("checkpointLocation", out).outputMode("append").start()
    run.awaitTermination()
    events.orderBy("ts").limit(10).write.mode("append").parquet(path)
    run = counts.writeStream.format("noop").trigger(availableNow=True).option("checkpointLocation", out).outputMode("append").start()
    run.awaitTermination()
    dropped = sum(int(op["numRowsDroppedByWatermark"]) for p in run.recentProgress for op in _operators(p))
    return spark.createDataFrame([(dropped,)], "n_dropped long")


def _operators(progress) -> list[dict]:
    """State operators of a progress report, as dictionaries."""
    import json

    return json.loads(progress if isinstance(progress, str) else progress.json)["stateOperators"]


def merge_components(known: DataFrame, edges: DataFrame) -> DataFrame:
    """New labels from known labels (vertex, component) and a batch of new edges (a, b)."""
    stars = known.select(F.col("vertex").alias("a"), F.col("component").alias("b"))
    return connected_components(stars.unionByName(edges.select("a", "b")), label="stream-cc")


def components_in_batches(pairs: DataFrame, batches: int = 3) -> DataFrame:
    """Components after pairs arrive in several batches; equals those of all pairs at once."""
    dealt = pairs.select("a", "b", F.pmod(F.xxhash64("a", "b"), F.lit(batches)).alias("k"))
    known = None
    for k in range(batches):
        new = dealt.where(F.col("k") == k).select("a", "b")
        known = connected_components(new, label="stream-cc") if known is None else merge_components(known, new)
    return known

