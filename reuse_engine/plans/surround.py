"""Surrounding operators on the given tables as named queries."""

from __future__ import annotations

import numpy as np
import pandas as pd
from pyspark.sql import DataFrame, SparkSession, Window
from pyspark.sql import functions as F
from pyspark.sql.functions import broadcast, pandas_udf, udtf

from reuse_engine.functions import symbols
from reuse_engine.functions.symbols import FNV_PRIME, FNV_START
from reuse_engine.operators import bundles, findings, homogeneity, pairing
from reuse_engine.plans import sqltext as S
from reuse_engine.plans.methods import fingers_of, norm_of, pairs_of, units_of
from reuse_engine.plans.registry import query
from reuse_engine.plans.workloads import DUPES, bundle_parts, cluster_parts, finding_parts
from reuse_engine.sources.artifacts import micros
from reuse_engine.storage import join_few, materialize, new_path, table


def _t(name: str):
    return lambda spark, d: table(spark, d, name)


docs, events, orders, items = _t("documents"), _t("events"), _t("orders"), _t("lineitem")

# --- scans, sources, sinks ---------------------------------------------------------------------


@query("q_scan_pruned", "SELECT doc_id, source, n_chars FROM documents")
def _(spark, d):
    return docs(spark, d).select("doc_id", "source", "n_chars")


@query("q_scan_pushdown", "SELECT event_id, user_id FROM events WHERE event_type = 'purchase' AND value > 100")
def _(spark, d):
    return events(spark, d).where("event_type = 'purchase' and value > 100").select("event_id", "user_id")


@query("q_scan_partitioned", S.with_(S.artifacts(["documents"]), "SELECT artifact_id, creator FROM art WHERE origin = 'direct'"))
def _(spark, d):
    rows = norm_of(spark, d, ["documents"]).select("artifact_id", "creator", "corpus", "origin")
    return materialize(rows, "partitioned", ["corpus", "origin"]).where("corpus = 'documents' and origin = 'direct'").select("artifact_id", "creator")


_TRIP = "SELECT doc_id, md5(text) AS text_hash FROM documents"


@query("q_source_json", _TRIP)
def _(spark, d):
    path, rows = new_path(spark, "json"), docs(spark, d).select("doc_id", "text")
    rows.write.json(path)
    return spark.read.schema(rows.schema).json(path).select("doc_id", F.md5("text").alias("text_hash"))


@query("q_source_csv", _TRIP)
def _(spark, d):
    path, rows = new_path(spark, "csv"), docs(spark, d).select("doc_id", F.regexp_replace(F.base64(F.encode("text", "UTF-8")), "\\s", "").alias("b"))
    rows.write.csv(path)
    return spark.read.schema(rows.schema).csv(path).select("doc_id", F.md5(F.unbase64("b")).alias("text_hash"))


@query("q_source_text", _TRIP)
def _(spark, d):
    path = new_path(spark, "text")
    docs(spark, d).select(F.concat(F.col("doc_id").cast("string"), F.lit(" "), F.regexp_replace(F.base64(F.encode("text", "UTF-8")), "\\s", ""))).write.text(path)
    cut = F.split("value", " ")
    return spark.read.text(path).select(cut[0].cast("bigint").alias("doc_id"), F.md5(F.unbase64(cut[1])).alias("text_hash"))


@query("q_source_binary")
def _(spark, d):
    """Hex programs written as text files and read back as binary ones."""
    path = new_path(spark, "binary")
    norm_of(spark, d, ["vm"]).select("runtime").repartition(4).write.text(path)
    files = spark.read.format("binaryFile").option("pathGlobFilter", "part-*").load(path)
    return files.select(F.explode_outer(F.split(F.decode("content", "UTF-8"), "\n")).alias("runtime")).where("runtime <> ''").select(F.md5("runtime").alias("runtime_hash"))


@query("q_sink_bucketed")
def _(spark, d):
    """Fingerprints bucketed by unit and joined with their pairs' sides without an exchange."""
    name = "fingers_" + new_path(spark, "x").rsplit("-", 1)[1]
    fps = units_of(spark, d, ["scripts"]).select("unit_id", "n_dup")
    fps.write.bucketBy(8, "unit_id").sortBy("unit_id").saveAsTable(name)
    stored = spark.table(name)
    return stored.join(stored.groupBy("unit_id").agg(F.max("n_dup").alias("m")), "unit_id").select("unit_id", "n_dup", "m")


# --- projections and filters ---------------------------------------------------------------------


@query("q_project_struct", S.with_(S.fingers(["scripts_week"]), "SELECT unit_id, n_ops, n_pieces FROM finger"))
def _(spark, d):
    packed = fingers_of(spark, d, ["scripts_week"]).select("unit_id", F.struct("n_ops", "n_pieces").alias("features"))
    return packed.select("unit_id", "features.*")


@query("q_filter_null_safe", "SELECT d.doc_id FROM documents d LEFT JOIN labels l ON l.doc_id = d.doc_id WHERE l.quality IS NOT DISTINCT FROM NULL")
def _(spark, d):
    return docs(spark, d).join(table(spark, d, "labels"), "doc_id", "left").where(F.col("quality").eqNullSafe(F.lit(None))).select("doc_id")


@query("q_filter_regex", r"SELECT doc_id FROM documents WHERE regexp_matches(text, '(?i)\n[^\n]*(licen[cs]e|rights reserved)[^\n]*\z')")
def _(spark, d):
    return docs(spark, d).where(F.col("text").rlike(r"(?i)\n[^\n]*(licen[cs]e|rights reserved)[^\n]*\z")).select("doc_id")


@query("q_filter_in_between", "SELECT event_id FROM events WHERE event_type IN ('view', 'error') AND value BETWEEN 10 AND 50")
def _(spark, d):
    return events(spark, d).where(F.col("event_type").isin("view", "error") & F.col("value").between(10, 50)).select("event_id")


# --- joins ----------------------------------------------------------------------------------------


@query("q_join_inner", "SELECT doc_id, epoch_us(ts) AS us FROM documents JOIN events ON event_id = doc_id")
def _(spark, d):
    return docs(spark, d).join(events(spark, d), F.col("event_id") == F.col("doc_id")).select("doc_id", micros("ts").alias("us"))


@query("q_join_broadcast", "SELECT r_name, count(*) AS n FROM customer JOIN nation ON c_nationkey = n_nationkey JOIN region ON n_regionkey = r_regionkey GROUP BY 1")
def _(spark, d):
    n = table(spark, d, "nation").join(broadcast(table(spark, d, "region")), F.col("n_regionkey") == F.col("r_regionkey"))
    return table(spark, d, "customer").join(broadcast(n), F.col("c_nationkey") == F.col("n_nationkey")).groupBy("r_name").agg(F.count("*").alias("n"))


_VOLUME = "SELECT o_orderkey, sum(round(l_extendedprice * 1000)::BIGINT)::BIGINT AS milli FROM orders JOIN lineitem ON o_orderkey = l_orderkey GROUP BY 1"


def _volume(hint: str):
    def run(spark, d):
        joined = orders(spark, d).select("o_orderkey").hint(hint).join(items(spark, d), F.col("o_orderkey") == F.col("l_orderkey"))
        return joined.groupBy("o_orderkey").agg(F.sum(F.round(F.col("l_extendedprice") * 1000).cast("bigint")).alias("milli"))

    return run


query("q_join_smj", _VOLUME)(_volume("merge"))
query("q_join_shuffle_hash", _VOLUME)(_volume("shuffle_hash"))


@query("q_join_left", "SELECT d.doc_id, l.toxic FROM documents d LEFT JOIN labels l ON l.doc_id = d.doc_id WHERE l.toxic IS NULL OR l.toxic = 1")
def _(spark, d):
    rows = docs(spark, d).join(table(spark, d, "labels"), "doc_id", "left")
    return rows.where("toxic is null or toxic = 1").select("doc_id", "toxic")


@query("q_join_full", "SELECT coalesce(doc_id, o_orderkey) AS id, doc_id IS NOT NULL AS has_doc, o_orderkey IS NOT NULL AS has_order FROM documents FULL JOIN (SELECT * FROM orders WHERE o_orderstatus = 'F') ON o_orderkey = doc_id")
def _(spark, d):
    o = orders(spark, d).where("o_orderstatus = 'F'")
    both = docs(spark, d).join(o, F.col("o_orderkey") == F.col("doc_id"), "full")
    return both.select(F.coalesce("doc_id", "o_orderkey").alias("id"), F.col("doc_id").isNotNull().alias("has_doc"), F.col("o_orderkey").isNotNull().alias("has_order"))


def _has_pair(how: str):
    def run(spark, d):
        fps, pairs, _ = cluster_parts(spark, d, "documents")
        ends = pairs.select(F.col("a").alias("unit_id")).union(pairs.select("b"))
        return fps.join(ends, "unit_id", how).select("unit_id")

    return run


_ENDS = "(SELECT a FROM pair UNION SELECT b FROM pair)"
query("q_join_semi", S.with_(S.pairs(["documents"]), f"SELECT unit_id FROM finger WHERE unit_id IN {_ENDS}"))(_has_pair("left_semi"))
query("q_join_anti", S.with_(S.pairs(["documents"]), f"SELECT unit_id FROM finger WHERE unit_id NOT IN {_ENDS}"))(_has_pair("left_anti"))

_P1_PAGES = S.with_(S.compared(["pages"]), "SELECT a, b FROM comp")


def _p1(how: str):
    return lambda spark, d: pairing.candidate_pairs(fingers_of(spark, d, ["pages"]), how, "length").select(F.col("unit_id_a").alias("a"), F.col("unit_id_b").alias("b"))


query("q_join_theta", _P1_PAGES)(_p1("theta"))
query("q_join_band", _P1_PAGES)(_p1("band"))


@query("q_join_interval", "SELECT s.event_id AS signup_id, count(e.event_id) AS n_after FROM events s JOIN events e ON e.user_id = s.user_id AND e.ts > s.ts AND e.ts <= s.ts + INTERVAL 1 HOUR WHERE s.event_type = 'signup' GROUP BY 1")
def _(spark, d):
    e = events(spark, d).select("user_id", "event_id", micros("ts").alias("us"), "event_type")
    s = e.where("event_type = 'signup'").select("user_id", F.col("event_id").alias("signup_id"), F.col("us").alias("s_us"))
    near = s.join(e, "user_id").where("us > s_us and us <= s_us + 3600000000")
    return near.groupBy("signup_id").agg(F.count("event_id").alias("n_after"))


@query("q_join_asof", "SELECT p.event_id, max(v.event_id) FILTER (WHERE v.ts = m.ts) AS view_id FROM (SELECT p.event_id, p.user_id, max(v.ts) AS ts FROM events p LEFT JOIN events v ON v.user_id = p.user_id AND v.event_type = 'view' AND v.ts <= p.ts WHERE p.event_type = 'purchase' GROUP BY ALL) m JOIN events p ON p.event_id = m.event_id LEFT JOIN events v ON v.user_id = p.user_id AND v.event_type = 'view' GROUP BY 1")
def _(spark, d):
    """Latest view before each purchase of a user: one ordered pass instead of a range join."""
    e = events(spark, d).where("event_type in ('view', 'purchase')").select("user_id", micros("ts").alias("us"), "event_id", "event_type")
    seen = F.last(F.when(F.col("event_type") == "view", F.col("event_id")), ignorenulls=True)
    order = Window.partitionBy("user_id").orderBy("us", F.desc("event_type"), "event_id").rowsBetween(Window.unboundedPreceding, 0)
    return e.withColumn("view_id", seen.over(order)).where("event_type = 'purchase'").select("event_id", "view_id")


@query("q_join_cross", "SELECT r_name, event_type FROM region, (SELECT DISTINCT event_type FROM events)")
def _(spark, d):
    return table(spark, d, "region").select("r_name").crossJoin(events(spark, d).select("event_type").distinct())


@query("q_join_self", "SELECT a, doc_id AS b FROM (SELECT doc_id, min(doc_id) OVER (PARTITION BY md5(text)) AS a FROM documents WHERE text IS NOT NULL) WHERE a < doc_id")
def _(spark, d):
    """A table joined with its own groups: each copy beside the first of its kind, not all pairs of a group."""
    x = docs(spark, d).where("text is not null").select(F.md5("text").alias("h"), F.col("doc_id").alias("b"))
    first = x.groupBy("h").agg(F.min("b").alias("a"), F.count("*").alias("n")).where("n > 1").select("h", "a")
    return join_few(x, materialize(first, "self-groups"), "h", F.xxhash64("b")).where("a < b").select("a", "b")


# --- aggregates -----------------------------------------------------------------------------------


@query("q_agg_hash", "SELECT source, count(*) AS n, min(n_chars) AS least, max(n_chars) AS most, sum(n_chars)::BIGINT // count(*) AS mean FROM documents GROUP BY 1")
def _(spark, d):
    g = docs(spark, d).groupBy("source").agg(F.count("*").alias("n"), F.min("n_chars").alias("least"), F.max("n_chars").alias("most"), F.sum("n_chars").alias("s"))
    return g.select("source", "n", "least", "most", F.expr("s div n").alias("mean"))


@query("q_agg_distinct", "SELECT ts::DATE::VARCHAR AS day, count(DISTINCT user_id) AS users, count(DISTINCT event_type) AS types FROM events GROUP BY 1")
def _(spark, d):
    return events(spark, d).groupBy(F.to_date("ts").cast("string").alias("day")).agg(F.countDistinct("user_id").alias("users"), F.countDistinct("event_type").alias("types"))


@query("q_agg_approx")
def _(spark, d):
    a = events(spark, d).agg(F.approx_count_distinct("user_id", 0.02).alias("approx"), F.countDistinct("user_id").alias("exact"), F.hll_sketch_estimate(F.hll_sketch_agg("user_id")).alias("sketch"))
    return a.withColumn("within_5", (F.abs(F.col("approx") - F.col("exact")) * 20 <= F.col("exact")) & (F.abs(F.col("sketch") - F.col("exact")) * 20 <= F.col("exact")))


@query("q_agg_percentile", S.with_(S.units(["scripts"]), "SELECT origin, quantile_disc(n_dup, 0.5) AS p50, quantile_disc(n_dup, 0.9) AS p90, max(n_dup) AS p100 FROM unit GROUP BY 1"))
def _(spark, d):
    u = units_of(spark, d, ["scripts"])
    return u.groupBy("origin").agg(*[F.expr(f"percentile_disc({p}) within group (order by n_dup)").cast("bigint").alias(n) for p, n in ((0.5, "p50"), (0.9, "p90"))], F.max("n_dup").alias("p100"))


@query("q_agg_percentile_approx")
def _(spark, d):
    return units_of(spark, d, ["scripts"]).groupBy("origin").agg(F.percentile_approx("n_dup", 0.9).alias("p90"), F.histogram_numeric("n_dup", F.lit(4)).alias("hist")).select("origin", "p90", F.size("hist").alias("bins"))


@query("q_agg_rollup", "SELECT lang, source, count(*) AS n FROM documents GROUP BY ROLLUP (lang, source)")
def _(spark, d):
    return docs(spark, d).rollup("lang", "source").agg(F.count("*").alias("n"))


@query("q_agg_cube", "SELECT quality::VARCHAR AS quality, toxic::VARCHAR AS toxic, count(*) AS n, grouping_id(quality, toxic)::BIGINT AS gid FROM labels GROUP BY CUBE (quality, toxic)")
def _(spark, d):
    c = table(spark, d, "labels").cube("quality", "toxic").agg(F.count("*").alias("n"), F.grouping_id().alias("gid"))
    return c.select(F.col("quality").cast("string"), F.col("toxic").cast("string"), "n", F.col("gid").cast("bigint").alias("gid"))


@query("q_agg_gsets", "SELECT lang, source, count(*) AS n FROM documents GROUP BY GROUPING SETS ((lang), (source), ())")
def _(spark, d):
    return spark.sql("select lang, source, count(*) as n from {t} group by grouping sets ((lang), (source), ())", t=docs(spark, d))


@query("q_agg_pivot", "SELECT user_id, count(*) FILTER (WHERE event_type = 'click') AS click, count(*) FILTER (WHERE event_type = 'view') AS \"view\" FROM events GROUP BY 1")
def _(spark, d):
    p = events(spark, d).groupBy("user_id").pivot("event_type", ["click", "view"]).count()
    return p.select("user_id", *[F.coalesce(F.col(c), F.lit(0)).alias(c) for c in ("click", "view")])


@query("q_agg_minby", S.with_(S.normalized(["scripts"]), f"SELECT token_hash, first(artifact_id ORDER BY coalesce(deployed_us, {S.LATEST}), artifact_id) AS first_id FROM norm GROUP BY 1"))
def _(spark, d):
    return norm_of(spark, d, ["scripts"]).groupBy("token_hash").agg(F.min_by("artifact_id", F.struct("deployed_us", "artifact_id")).alias("first_id"))


@query("q_agg_filter", "SELECT source, count(*) FILTER (WHERE n_chars > 1000) AS large, count(*) FILTER (WHERE lang = 'en') AS english FROM documents GROUP BY 1")
def _(spark, d):
    return spark.sql("select source, count_if(n_chars > 1000) as large, count(*) filter (where lang = 'en') as english from {t} group by source", t=docs(spark, d))


@query("q_agg_collect", S.with_(f"{S.pairs(['documents'])},\n{S.components()}", "SELECT l AS cluster_id, string_agg(v, ',' ORDER BY v) AS members FROM label GROUP BY 1"))
def _(spark, d):
    cl = cluster_parts(spark, d, "documents")[2]
    return cl.groupBy("cluster_id").agg(F.array_join(F.sort_array(F.collect_set("unit_id")), ",").alias("members"))


# --- windows --------------------------------------------------------------------------------------

_UNIT = S.units(["scripts"])


@query("q_win_rank", S.with_(_UNIT, "SELECT origin, token_hash, row_number() OVER w AS rn, rank() OVER v AS rk, dense_rank() OVER v AS dr, ntile(4) OVER w AS nt FROM unit WINDOW w AS (PARTITION BY origin ORDER BY n_dup DESC, token_hash), v AS (PARTITION BY origin ORDER BY n_dup DESC)"))
def _(spark, d):
    w, v = Window.partitionBy("origin").orderBy(F.desc("n_dup"), "token_hash"), Window.partitionBy("origin").orderBy(F.desc("n_dup"))
    fs = {"rn": F.row_number().over(w), "rk": F.rank().over(v), "dr": F.dense_rank().over(v), "nt": F.ntile(4).over(w)}
    return units_of(spark, d, ["scripts"]).select("origin", "token_hash", *[c.cast("bigint").alias(k) for k, c in fs.items()])


@query("q_win_dist", S.with_(_UNIT, "SELECT token_hash, origin, round(percent_rank() OVER v * 10000)::BIGINT AS pr, round(cume_dist() OVER v * 10000)::BIGINT AS cd FROM unit WINDOW v AS (PARTITION BY origin ORDER BY n_dup)"))
def _(spark, d):
    v = Window.partitionBy("origin").orderBy("n_dup")
    return units_of(spark, d, ["scripts"]).select("token_hash", "origin", F.round(F.percent_rank().over(v) * 10000).cast("bigint").alias("pr"), F.round(F.cume_dist().over(v) * 10000).cast("bigint").alias("cd"))


@query("q_win_running", S.with_(_UNIT, "SELECT origin, token_hash, sum(n_dup) OVER (PARTITION BY origin ORDER BY n_dup DESC, token_hash ROWS UNBOUNDED PRECEDING)::BIGINT AS cum FROM unit"))
def _(spark, d):
    w = Window.partitionBy("origin").orderBy(F.desc("n_dup"), "token_hash").rowsBetween(Window.unboundedPreceding, 0)
    return units_of(spark, d, ["scripts"]).select("origin", "token_hash", F.sum("n_dup").over(w).alias("cum"))


@query("q_win_range", "SELECT event_id, count(*) OVER (PARTITION BY user_id ORDER BY epoch_us(ts) RANGE BETWEEN 604800000000 PRECEDING AND CURRENT ROW) AS n_week FROM events")
def _(spark, d):
    w = Window.partitionBy("user_id").orderBy("us").rangeBetween(-7 * 86_400_000_000, 0)
    return events(spark, d).withColumn("us", micros("ts")).select("event_id", F.count("*").over(w).alias("n_week"))


@query("q_win_lag", "SELECT event_id, epoch_us(ts) - lag(epoch_us(ts)) OVER w AS gap, lead(event_id) OVER w AS next_id FROM events WINDOW w AS (PARTITION BY user_id ORDER BY epoch_us(ts), event_id)")
def _(spark, d):
    w = Window.partitionBy("user_id").orderBy("us", "event_id")
    return events(spark, d).withColumn("us", micros("ts")).select("event_id", (F.col("us") - F.lag("us").over(w)).alias("gap"), F.lead("event_id").over(w).alias("next_id"))


@query("q_win_first_last", "SELECT DISTINCT user_id, first_value(event_id) OVER w AS first_id, last_value(event_id) OVER w AS last_id, nth_value(event_id, 2) OVER w AS second_id FROM events WINDOW w AS (PARTITION BY user_id ORDER BY epoch_us(ts), event_id ROWS BETWEEN UNBOUNDED PRECEDING AND UNBOUNDED FOLLOWING)")
def _(spark, d):
    w = Window.partitionBy("user_id").orderBy("us", "event_id").rowsBetween(Window.unboundedPreceding, Window.unboundedFollowing)
    e = events(spark, d).withColumn("us", micros("ts"))
    return e.select("user_id", F.first("event_id").over(w).alias("first_id"), F.last("event_id").over(w).alias("last_id"), F.nth_value("event_id", 2).over(w).alias("second_id")).distinct()


@query("q_topk", S.with_(_UNIT, "SELECT token_hash, origin, n_dup FROM unit ORDER BY n_dup DESC, token_hash, origin LIMIT 10"))
def _(spark, d):
    return units_of(spark, d, ["scripts"]).select("token_hash", "origin", "n_dup").orderBy(F.desc("n_dup"), "token_hash", "origin").limit(10)


@query("q_topk_group", S.with_(_UNIT, "SELECT origin, token_hash, r AS rank FROM (SELECT *, row_number() OVER (PARTITION BY origin ORDER BY n_dup DESC, token_hash) AS r FROM unit) WHERE r <= 3"))
def _(spark, d):
    return homogeneity.top_groups(units_of(spark, d, ["scripts"]), "n_dup", 3, ("origin",), "token_hash").select("origin", "token_hash", "rank")


@query("q_offset", S.with_(_UNIT, "SELECT token_hash, origin FROM unit ORDER BY n_dup DESC, token_hash, origin LIMIT 10 OFFSET 10"))
def _(spark, d):
    return units_of(spark, d, ["scripts"]).orderBy(F.desc("n_dup"), "token_hash", "origin").offset(10).limit(10).select("token_hash", "origin")


# --- sets -----------------------------------------------------------------------------------------


@query("q_set_union", S.with_(S.units(["pages", "documents"]), "SELECT token_hash FROM unit"))
def _(spark, d):
    return units_of(spark, d, ["pages"]).select("token_hash").unionByName(units_of(spark, d, ["documents"]).select("token_hash"))


@query("q_set_union_distinct", S.with_(S.normalized(["pages", "documents"]), "SELECT DISTINCT corpus, token_hash FROM norm"))
def _(spark, d):
    return norm_of(spark, d, ["pages", "documents"]).select("corpus", "token_hash").distinct()


@query("q_set_intersect", S.with_(_UNIT, "SELECT tok FROM unit WHERE origin = 'direct' INTERSECT SELECT tok FROM unit WHERE origin = 'factory'"))
def _(spark, d):
    u = materialize(units_of(spark, d, ["scripts"]).select("origin", "tok"), "units")
    return u.where("origin = 'direct'").select("tok").intersect(u.where("origin = 'factory'").select("tok"))


@query("q_set_except", S.with_(_UNIT, "SELECT tok FROM unit WHERE origin = 'direct' EXCEPT SELECT tok FROM unit WHERE origin = 'factory'"))
def _(spark, d):
    u = materialize(units_of(spark, d, ["scripts"]).select("origin", "tok"), "units")
    return u.where("origin = 'direct'").select("tok").exceptAll(u.where("origin = 'factory'").select("tok"))


# --- functions ------------------------------------------------------------------------------------


@query("q_str_basic", "SELECT doc_id, md5(lower(trim(text, ' '))) AS h, len(string_split(text, ' ')) AS parts, substr(text, 1, 5) AS head, lang || '-' || source AS tag FROM documents")
def _(spark, d):
    return docs(spark, d).select("doc_id", F.md5(F.lower(F.trim("text"))).alias("h"), F.size(F.split("text", " ")).cast("bigint").alias("parts"), F.substring("text", 1, 5).alias("head"), F.concat_ws("-", "lang", "source").alias("tag"))


@query("q_str_url", "SELECT page_id, regexp_extract(url, '^([a-z]+)://', 1) AS scheme, regexp_extract(url, '^https?://([^/?#]+)', 1) AS host, regexp_extract(url, '^https?://[^/?#]+([^?#]*)', 1) AS path, regexp_extract(url, '[?]([^#]*)', 1) AS q FROM pages")
def _(spark, d):
    parts = {"scheme": "^([a-z]+)://", "host": "^https?://([^/?#]+)", "path": "^https?://[^/?#]+([^?#]*)", "q": "[?]([^#]*)"}
    return table(spark, d, "pages").select("page_id", *[F.regexp_extract("url", p, 1).alias(n) for n, p in parts.items()])


@query("q_str_url_builtin")
def _(spark, d):
    return table(spark, d, "pages").select("page_id", *[F.parse_url("url", F.lit(p)).alias(p.lower()) for p in ("PROTOCOL", "HOST", "PATH", "QUERY")])


@query("q_str_hash", "SELECT doc_id, md5(text) AS m, sha256(text) AS s FROM documents")
def _(spark, d):
    return docs(spark, d).select("doc_id", F.md5("text").alias("m"), F.sha2("text", 256).alias("s"))


@query("q_str_distance", "SELECT x.p_partkey AS a, y.p_partkey AS b, levenshtein(x.p_name, y.p_name) AS dist FROM part x JOIN part y ON x.p_partkey + 1 = y.p_partkey")
def _(spark, d):
    p = table(spark, d, "part").select("p_partkey", "p_name")
    y = p.select((F.col("p_partkey") - 1).alias("p_partkey"), F.col("p_name").alias("other"))
    return p.join(y, "p_partkey").select(F.col("p_partkey").alias("a"), (F.col("p_partkey") + 1).alias("b"), F.levenshtein("p_name", "other").cast("bigint").alias("dist"))


@query("q_hex", "SELECT p_partkey, hex(p_name) AS h, decode(unhex(hex(p_name))) AS back, to_base64(encode(p_name)) AS b64 FROM part")
def _(spark, d):
    return table(spark, d, "part").select("p_partkey", F.hex(F.encode("p_name", "UTF-8")).alias("h"), F.decode(F.unhex(F.hex("p_name")), "UTF-8").alias("back"), F.base64(F.encode("p_name", "UTF-8")).alias("b64"))


@query("q_date", "SELECT strftime(o_orderdate, '%Y-%m') AS month, count(*) AS n, max(date_diff('day', DATE '1992-01-01', o_orderdate::DATE)) AS days FROM orders GROUP BY 1")
def _(spark, d):
    o = orders(spark, d).groupBy(F.date_format("o_orderdate", "yyyy-MM").alias("month"))
    return o.agg(F.count("*").alias("n"), F.max(F.datediff(F.to_date("o_orderdate"), F.lit("1992-01-01").cast("date"))).cast("bigint").alias("days"))


@query("q_math", "SELECT o_orderkey, o_orderkey // 7 AS q, o_orderkey % 7 AS r, floor(ln(o_orderkey + 1) / ln(2.0))::BIGINT AS bucket, greatest(o_orderkey % 5, o_orderkey % 3) AS g FROM orders")
def _(spark, d):
    k = F.col("o_orderkey")
    return orders(spark, d).select("o_orderkey", F.expr("o_orderkey div 7").alias("q"), F.pmod(k, F.lit(7)).alias("r"), F.floor(F.log((k + 1).cast("double")) / F.log(F.lit(2.0))).cast("bigint").alias("bucket"), F.greatest(k % 5, k % 3).alias("g"))


@query("q_array", S.with_(S.fingers(["scripts"]), "SELECT unit_id, origin, i - 1 AS pos, pieces[i] AS piece FROM finger, range(1, 1000) r(i) WHERE i <= len(pieces)"))
def _(spark, d):
    from reuse_engine.operators.fingerprints import pieces

    return pieces(units_of(spark, d, ["scripts"]), "script").select("unit_id", "origin", F.posexplode("pieces").alias("pos", "piece")).select("unit_id", "origin", F.col("pos").cast("bigint").alias("pos"), "piece")


@query("q_array_hof", "SELECT vec_id, len(list_filter(embedding, lambda x: x > 0)) AS n_pos, len(list_filter(list_zip(embedding[1:63], embedding[2:64]), lambda p: (p[1] > 0) <> (p[2] > 0))) AS n_flips FROM embeddings")
def _(spark, d):
    e = table(spark, d, "embeddings")
    flips = F.zip_with(F.slice("embedding", 1, 63), F.slice("embedding", 2, 63), lambda a, b: ((a > 0) != (b > 0)).cast("bigint"))
    return e.select("vec_id", F.size(F.filter("embedding", lambda x: x > 0)).cast("bigint").alias("n_pos"), F.aggregate(flips, F.lit(0).cast("bigint"), lambda s, x: s + x).alias("n_flips"))


@query("q_map", "SELECT user_id, list_sort(list(DISTINCT event_type))[1] AS first_kind, count(DISTINCT event_type) AS n_kinds FROM events GROUP BY 1")
def _(spark, d):
    per = events(spark, d).groupBy("user_id", "event_type").agg(F.count("*").alias("n"))
    m = per.groupBy("user_id").agg(F.map_from_entries(F.collect_list(F.struct("event_type", "n"))).alias("m"))
    return m.select("user_id", F.array_min(F.map_keys("m")).alias("first_kind"), F.size("m").cast("bigint").alias("n_kinds"))


@query("q_json", "SELECT event_type, sum((props->>'$.k')::BIGINT)::BIGINT AS k FROM events GROUP BY 1")
def _(spark, d):
    return events(spark, d).groupBy("event_type").agg(F.sum(F.from_json("props", "k bigint")["k"]).alias("k"))


@query("q_lateral", S.with_(S.pairs(["documents"]), "SELECT unit_id, other, score_bp::BIGINT AS score_bp FROM (SELECT *, row_number() OVER (PARTITION BY unit_id ORDER BY score_bp DESC, other) AS r FROM (SELECT a AS unit_id, b AS other, score_bp FROM pair UNION ALL SELECT b, a, score_bp FROM pair)) WHERE r <= 2"))
def _(spark, d):
    pairs = pairing.similar_pairs(fingers_of(spark, d, ["documents"]))
    both = pairs.select(F.col("a").alias("unit_id"), F.col("b").alias("other"), "score_bp").unionByName(pairs.select(F.col("b").alias("unit_id"), F.col("a").alias("other"), "score_bp"))
    return both.withColumn("r", F.row_number().over(Window.partitionBy("unit_id").orderBy(F.desc("score_bp"), "other"))).where("r <= 2").drop("r")


@query("q_cte_recursive", S.with_(f"{S.pairs(['documents'])},\n{S.components()}", "SELECT v, l FROM label"))
def _(spark, d):
    """Reachability in SQL: every vertex hangs under its least neighbour, a recursive query walks these trees from their roots, and roots that edges still join go on."""
    return recursive_labels(spark, pairs_of(spark, d, ["documents"]).select("a", "b"))


_UNLIMITED = ("spark.sql.cteRecursionLevelLimit", "spark.sql.cteRecursionRowLimit")


def recursive_labels(spark: SparkSession, edges: DataFrame) -> DataFrame:
    """(v, l): least member of the component of every vertex of ``edges`` (a, b); a walk visits a vertex once, so its rows are the vertices."""
    before = {key: spark.conf.get(key) for key in _UNLIMITED}
    edges, label = materialize(edges.select(F.col("a").alias("p"), F.col("b").alias("q")).where("p <> q"), "cte-edges"), None
    try:
        for key in _UNLIMITED:
            spark.conf.set(key, "-1")
        while edges.head(1):
            both = edges.unionByName(edges.select(F.col("q").alias("p"), F.col("p").alias("q")))
            up = materialize(both.groupBy("p").agg(F.least("p", F.min("q")).alias("h")), "cte-up")
            up.createOrReplaceTempView("reuse_up")
            walked = spark.sql("""with recursive reach(v, l) as (select p, p from reuse_up where h = p
              union all select u.p, r.l from reach r join reuse_up u on u.h = r.v and u.p <> u.h) select v, l from reach""")
            roots = materialize(walked, "cte-roots")
            if label is None:
                label = roots
            else:
                moved = label.join(roots.toDF("l", "to"), "l", "left").select("v", F.coalesce("to", "l").alias("l"))
                label = materialize(moved, "cte-label")
            x, y = roots.toDF("p", "x"), roots.toDF("q", "y")
            joined = edges.join(x, "p").join(y, "q").where("x <> y").select(F.col("x").alias("p"), F.col("y").alias("q")).distinct()
            edges = materialize(joined, "cte-edges")
    finally:
        for key, value in before.items():
            spark.conf.set(key, value)
    return edges.toDF("v", "l") if label is None else label


@query("q_sql_udf", "SELECT m AS max_len, (10000 * (m - 3)) // m AS bp FROM range(3, 40) r(m)")
def _(spark, d):
    spark.sql("create or replace temporary function similarity_bp(d bigint, m bigint) returns bigint return (10000 * (m - d)) div m")
    return spark.sql("select id as max_len, similarity_bp(3L, id) as bp from range(3, 40)")


def fnv1a32(texts: pd.Series) -> pd.Series:
    """32-bit FNV-1a of UTF-8 bytes over a batch: step k folds byte k of every text that has one."""
    known = texts.dropna()
    raw = [t.encode() for t in known]
    sizes = np.array([len(r) for r in raw], np.int64)
    flat, start = np.frombuffer(b"".join(raw), np.uint8).astype(np.uint64), np.concatenate([[0], np.cumsum(sizes)[:-1]]) if raw else np.zeros(0, np.int64)
    h = np.full(len(raw), FNV_START, np.uint64)
    left = np.flatnonzero(sizes > 0)
    k = 0
    while len(left):
        h[left] = ((h[left] ^ flat[start[left] + k]) * np.uint64(FNV_PRIME)) & np.uint64(0xFFFFFFFF)
        k += 1
        left = left[sizes[left] > k]
    return pd.Series(h.astype(np.int64), index=known.index, dtype="Int64").reindex(texts.index)


@query("q_udf_scalar")
def _(spark, d):
    """A vectorised function beside the built-in expression for the same hash; ``same`` is true for all."""
    u = units_of(spark, d, ["scripts"])
    return u.select("unit_id", "origin", pandas_udf(fnv1a32, "long")("tok").alias("fnv"), symbols.fnv1a32(F.col("tok")).alias("built_in")).withColumn("same", F.col("fnv") == F.col("built_in"))


def gini(sizes: pd.Series) -> float:
    s = sizes.sort_values().reset_index(drop=True)
    n = len(s)
    return float((2 * (s * (s.index + 1)).sum()) / (n * s.sum()) - (n + 1) / n) if n and s.sum() else 0.0


@query("q_udf_agg")
def _(spark, d):
    """Gini coefficient of group sizes, on the histogram's few rows per origin."""
    return units_of(spark, d, ["scripts"]).groupBy("origin").agg(pandas_udf(gini, "double")("n_dup").alias("gini"))


class CutPieces:
    """Text to (position, piece); pieces end with p or e."""

    def eval(self, text: str):
        piece, pos = "", 0
        for c in text or "":
            piece += c
            if c in "pe":
                yield pos, piece
                piece, pos = "", pos + 1
        if piece:
            yield pos, piece


@query("q_udtf_pieces")
def _(spark, d):
    units_of(spark, d, ["scripts"]).select("unit_id", "tok").createOrReplaceTempView("reuse_units")
    spark.udtf.register("cut_pieces", udtf(CutPieces, returnType="pos int, piece string"))
    return spark.sql("select unit_id, pos, piece from reuse_units, lateral cut_pieces(tok)")


@query("q_grouped_map")
def _(spark, d):
    mem, bun = bundle_parts(spark, d, "pages")
    w = bundles.bipartite(mem, bun, pairing.similar_pairs(fingers_of(spark, d, ["pages"]), 90))
    return bundles.match_bundles(bundles.bounded_pairs(w, bundles.bundle_sizes(mem), 0)).select("ua", "ub", "total_bp", "matched")


@query("q_map_arrow", S.with_(S.normalized(["vm"]), "SELECT artifact_id, length(runtime) // 2 AS n_bytes FROM norm"))
def _(spark, d):
    """Bulk hex decoding of programs in Arrow batches."""
    import pyarrow as pa

    def run(batches):
        for b in batches:
            sizes = [len(bytes.fromhex(x)) for x in b.column(1).to_pylist()]
            yield pa.RecordBatch.from_arrays([b.column(0), pa.array(sizes, pa.int64())], names=["artifact_id", "n_bytes"])

    return norm_of(spark, d, ["vm"]).select("artifact_id", "runtime").mapInArrow(run, "artifact_id string, n_bytes long")


@query("q_sample_strata", S.with_(S.compared(["pages"]), "SELECT bin, a, b FROM (SELECT *, score_bp // 1000 AS bin, row_number() OVER (PARTITION BY score_bp // 1000 ORDER BY md5(a || '|' || b), a, b) AS r FROM comp) WHERE r <= 100"))
def _(spark, d):
    s = pairing.scored(pairing.candidate_pairs(fingers_of(spark, d, ["pages"]), "band", "length")).withColumn("bin", F.expr("score_bp div 1000"))
    w = Window.partitionBy("bin").orderBy(F.md5(F.concat("a", F.lit("|"), "b")), "a", "b")
    return s.withColumn("r", F.row_number().over(w)).where("r <= 100").select("bin", "a", "b")


@query("q_sql_views", S.with_(S.units(DUPES), "SELECT corpus, count(*) AS n_units, sum(n_dup)::BIGINT AS n_artifacts FROM unit GROUP BY 1"))
def _(spark, d):
    """The SQL surface: views over the engine's tables."""
    register_views(spark, d, DUPES)
    return spark.sql("select corpus, count(*) as n_units, sum(n_dup) as n_artifacts from units group by corpus")


def register_views(spark: SparkSession, d: str, corpora: list[str]) -> dict[str, DataFrame]:
    """Temporary views of all seven tables: artifacts (normalized), units, fingerprints, pairs, clusters, findings and bundles (the last three of documents)."""
    made = {"artifacts": norm_of(spark, d, corpora), "units": units_of(spark, d, corpora), "fingerprints": fingers_of(spark, d, corpora), "pairs": pairs_of(spark, d, corpora)}
    made["clusters"], made["findings"], made["bundles"] = cluster_parts(spark, d, "documents")[2], finding_parts(spark, d)[1], bundle_parts(spark, d, "documents")[1]
    for name, df in made.items():
        df.createOrReplaceTempView(name)
    return made


@query("q_sql_views_findings", S.with_(f"{S.pairs(['documents'])}, {S.findings()},\n{S.components()}", "SELECT l AS cluster_id, ftype, count(*) AS n_units, sum(n)::BIGINT AS n_findings FROM label JOIN found ON unit_id = v GROUP BY ALL"))
def _(spark, d):
    """Findings by cluster, in SQL over the views."""
    register_views(spark, d, ["documents"])
    return spark.sql("select cluster_id, ftype, count(*) as n_units, sum(n) as n_findings from clusters join findings using (unit_id) group by cluster_id, ftype")
