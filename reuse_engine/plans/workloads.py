"""The experiment workloads, measures and cluster, finding and bundle methods as named queries."""

from __future__ import annotations

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from reuse_engine import graph
from reuse_engine.operators import bundles, calibration, findings, homogeneity, pairing, preprocess
from reuse_engine.plans import sqltext as S
from reuse_engine.plans.methods import _vm_fp_sql, _vm_fps, _fixture_sql, fingers_of, norm_of, pairs_of, prints_of, texts_of, union, units_of
from reuse_engine.plans.registry import query
from reuse_engine.sources.artifacts import CORPORA, payloads
from reuse_engine.storage import materialize, shared_table, table

DUPES = ["scripts", "pages", "documents"]
PAIRED = ["documents", "pages", "scripts_week"]
#: Corpus: threshold for clusters. Pages form one component at 70, so they are clustered at 90.
CLUSTERED = {"documents": 70, "pages": 90, "scripts_week": 70}
MIN_FP = 4


# --- dataset and duplicates ---------------------------------------------------------------


_OVERVIEW = S.with_(S.normalized(DUPES), """SELECT corpus, origin, count(*) AS n_artifacts, count(DISTINCT creator) AS n_creators,
  count(DISTINCT runtime_hash) AS n_stage1, count(DISTINCT token_hash) AS n_stage2 FROM norm GROUP BY ALL""")


@query("w01_overview", _OVERVIEW)
def _w01(spark, d):
    return norm_of(spark, d, DUPES).groupBy("corpus", "origin").agg(
        F.count("*").alias("n_artifacts"), F.countDistinct("creator").alias("n_creators"),
        F.countDistinct("runtime_hash").alias("n_stage1"), F.countDistinct("token_hash").alias("n_stage2"),
    )


@query("c01_corpus_overview", S.with_(S.artifacts(DUPES), "SELECT corpus, origin, count(*) AS n_artifacts, count(DISTINCT creator) AS n_creators FROM art GROUP BY ALL"))
def _c01(spark, d):
    return _w01(spark, d).select("corpus", "origin", "n_artifacts", "n_creators")


@query("c02_unfingerprinted", S.with_(S.fingers(PAIRED), "SELECT corpus, origin, count(*) AS n_units, count(*) FILTER (WHERE fp_len = 0) AS n_unfingerprinted FROM finger GROUP BY ALL"))
def _c02u(spark, d):
    """Units without a piece, which no pair can hold."""
    return fingers_of(spark, d, PAIRED).groupBy("corpus", "origin").agg(F.count("*").alias("n_units"), F.count_if(F.col("fp_len") == 0).alias("n_unfingerprinted"))


@query("c02_stage_counts", S.with_(S.normalized(DUPES), "SELECT corpus, origin, count(DISTINCT runtime_hash) AS n_stage1, count(DISTINCT token_hash) AS n_stage2 FROM norm GROUP BY ALL"))
def _c02(spark, d):
    return _w01(spark, d).select("corpus", "origin", "n_stage1", "n_stage2")


_SHRINK = S.with_(S.normalized(DUPES), """SELECT corpus, origin, sum(n)::BIGINT AS n_artifacts, count(*) AS n_units, (10000 * count(*)) // sum(n)::BIGINT AS shrink_bp
  FROM (SELECT corpus, origin, token_hash, count(*) AS n FROM norm GROUP BY ALL) GROUP BY ROLLUP (corpus, origin)""")


@query("w02_shrink", _SHRINK)
@query("c03_shrink", _SHRINK)
def _w02(spark, d):
    groups = norm_of(spark, d, DUPES).groupBy("corpus", "origin", "token_hash").agg(F.count("*").alias("n"))
    rolled = groups.rollup("corpus", "origin").agg(F.sum("n").cast("bigint").alias("n_artifacts"), F.count("*").alias("n_units"))
    return rolled.withColumn("shrink_bp", F.expr("(10000 * n_units) div n_artifacts"))


@query("w03_dup_distribution", S.with_(S.units(["scripts"]), """SELECT origin, group_size, n_groups, n_artifacts, sum(n_artifacts) OVER (PARTITION BY origin ORDER BY group_size DESC)::BIGINT AS cum_artifacts
  FROM (SELECT origin, n_dup AS group_size, count(*) AS n_groups, sum(n_dup)::BIGINT AS n_artifacts FROM unit GROUP BY ALL)"""))
def _w03(spark, d):
    hist = homogeneity.size_histogram(units_of(spark, d, ["scripts"]), "n_dup", ("origin",))
    return hist.select("origin", "group_size", "n_groups", F.col("n_members").alias("n_artifacts"), F.col("cum_members").alias("cum_artifacts"))


_TOP10 = S.with_(S.units(["scripts"]), """SELECT origin, r AS rank, token_hash, n_dup, substr(tok, 1, 1) AS label, (10000 * n_dup) // total AS share_bp
  FROM (SELECT *, row_number() OVER (PARTITION BY origin ORDER BY n_dup DESC, token_hash) AS r, sum(n_dup) OVER (PARTITION BY origin)::BIGINT AS total FROM unit) WHERE r <= 10""")


@query("w04_top10_dups", _TOP10)
def _w04(spark, d):
    u = materialize(units_of(spark, d, ["scripts"]).select("origin", "token_hash", "n_dup", F.substring("tok", 1, 1).alias("label")), "units")
    total = u.groupBy("origin").agg(F.sum("n_dup").cast("bigint").alias("total"))
    top = homogeneity.top_groups(u, "n_dup", 10, ("origin",), "token_hash").join(F.broadcast(total), "origin")
    return top.select("origin", "rank", "token_hash", "n_dup", "label", F.expr("(10000 * n_dup) div total").alias("share_bp"))


@query("c05_top_k_share", f"SELECT origin, (10000 * sum(n)) // any_value(total) AS share_bp FROM (SELECT origin, n_dup::HUGEINT AS n, (SELECT sum(n_dup) FROM ({S.with_(S.units(['scripts']), 'SELECT origin, n_dup FROM unit')}) z WHERE z.origin = t.origin) AS total FROM ({_TOP10}) t) GROUP BY origin".replace("(10000 * sum(n)) // any_value(total)", "((10000 * sum(n)) // any_value(total))::BIGINT"))
def _c05(spark, d):
    u = materialize(units_of(spark, d, ["scripts"]).select("origin", "token_hash", "n_dup"), "units")
    total = u.groupBy("origin").agg(F.sum("n_dup").cast("bigint").alias("total"))
    top = homogeneity.top_groups(u, "n_dup", 10, ("origin",), "token_hash").groupBy("origin").agg(F.sum("n_dup").cast("bigint").alias("held"))
    return top.join(total, "origin").select("origin", F.expr("(10000 * held) div total").alias("share_bp"))


def _dup_sql(by: str, stage: str) -> str:
    return f"SELECT corpus, origin, '{stage}' AS stage, (10000 * sum(CASE WHEN n >= 2 THEN n ELSE 0 END)::BIGINT) // sum(n)::BIGINT AS dup_share_bp FROM (SELECT corpus, origin, {by}, count(*) AS n FROM norm GROUP BY ALL) GROUP BY corpus, origin"


_DUP = S.with_(S.normalized(DUPES), f"{_dup_sql('runtime_hash', 'stage1')} UNION ALL {_dup_sql('token_hash', 'stage2')}")


@query("w05_dup_share", _DUP)
@query("c04_dup_share", _DUP)
@query("m48_dup_share", _DUP)
def _w05(spark, d):
    norm = materialize(norm_of(spark, d, DUPES).select("corpus", "origin", "runtime_hash", "token_hash"), "hashes")
    return homogeneity.duplication_metrics(norm, "runtime_hash", "stage1").unionByName(homogeneity.duplication_metrics(norm, "token_hash", "stage2"))


# --- pairs ----------------------------------------------------------------------------------


_COUNTS = S.with_(S.compared(PAIRED), """SELECT u.corpus, u.origin, u.n_units, u.n_units * (u.n_units - 1) // 2 AS n_possible, coalesce(c.n, 0) AS n_compared, coalesce(c.s, 0) AS n_similar
  FROM (SELECT corpus, origin, count(*) AS n_units FROM finger WHERE fp_len > 0 GROUP BY ALL) u
  LEFT JOIN (SELECT corpus, origin, count(*) AS n, count(*) FILTER (WHERE 100 * (max_len - dist) >= 70 * max_len) AS s FROM comp GROUP BY ALL) c ON c.corpus = u.corpus AND c.origin = u.origin""")


@query("w06_pair_counts", _COUNTS)
@query("c06_pair_counts", _COUNTS)
def _w06(spark, d):
    fps = fingers_of(spark, d, PAIRED)
    similar = pairs_of(spark, d, PAIRED).groupBy("corpus", "origin").agg(F.count("*").alias("n_similar"))
    return pairing.compared_counts(fps).join(similar, ["corpus", "origin"], "left").withColumn("n_similar", F.coalesce("n_similar", F.lit(0)))


@query("c07_narrowing", f"SELECT c.corpus, c.origin, (n_possible * 100) // greatest(n_compared, 1) AS vs_units_pct, (a.n * (a.n - 1) // 2 * 100) // greatest(n_compared, 1) AS vs_raw_pct FROM ({_COUNTS}) c JOIN (SELECT corpus, origin, count(*) AS n FROM ({S.with_(S.artifacts(PAIRED), 'SELECT corpus, origin FROM art')}) GROUP BY ALL) a ON a.corpus = c.corpus AND a.origin = c.origin")
def _c07(spark, d):
    counts = pairing.compared_counts(fingers_of(spark, d, PAIRED))
    raw = norm_of(spark, d, PAIRED).groupBy("corpus", "origin").agg(F.count("*").alias("n"))
    joined = counts.join(raw, ["corpus", "origin"])
    return joined.selectExpr("corpus", "origin", "(n_possible * 100) div greatest(n_compared, 1) as vs_units_pct", "((n * (n - 1) div 2) * 100) div greatest(n_compared, 1) as vs_raw_pct")


_HIST = S.with_(S.compared(PAIRED), """SELECT corpus, origin, least(score_bp // 1000, 9) * 10 AS bin, count(*) AS n_pairs FROM comp GROUP BY ALL
  UNION ALL SELECT u.corpus, u.origin, -1, u.n * (u.n - 1) // 2 - coalesce(c.n, 0) FROM (SELECT corpus, origin, count(*) AS n FROM finger WHERE fp_len > 0 GROUP BY ALL) u
  LEFT JOIN (SELECT corpus, origin, count(*) AS n FROM comp GROUP BY ALL) c ON c.corpus = u.corpus AND c.origin = u.origin""")


@query("w07_score_hist", _HIST)
@query("c08_score_histogram", _HIST)
def _w07(spark, d):
    """Compared pairs by score, and in bin -1 the pairs that pruning spares, counted from lengths alone."""
    fps = fingers_of(spark, d, PAIRED)
    s = pairing.scored(pairing.candidate_pairs(fps, "band", "length"))
    bins = s.groupBy("corpus", "origin", (F.least(F.expr("score_bp div 1000"), F.lit(9)) * 10).alias("bin")).agg(F.count("*").alias("n_pairs"))
    spared = pairing.compared_counts(fps).select("corpus", "origin", F.lit(-1).cast("bigint").alias("bin"), (F.col("n_possible") - F.col("n_compared")).alias("n_pairs"))
    return bins.unionByName(spared)


@query("c09_identical_fp", S.with_(S.pairs(PAIRED), "SELECT corpus, origin, count(*) FILTER (WHERE dist = 0) AS n_identical FROM pair GROUP BY ALL"))
def _c09(spark, d):
    return pairs_of(spark, d, PAIRED).groupBy("corpus", "origin").agg(F.count_if(F.col("dist") == 0).alias("n_identical"))


@query("c10_involved", S.with_(S.pairs(PAIRED), "SELECT u.corpus, u.origin, n_units, coalesce(n, 0) AS n_involved, (10000 * coalesce(n, 0)) // n_units AS involved_bp FROM (SELECT corpus, origin, count(*) AS n_units FROM finger GROUP BY ALL) u LEFT JOIN (SELECT corpus, origin, count(DISTINCT v) AS n FROM (SELECT corpus, origin, a AS v FROM pair UNION ALL SELECT corpus, origin, b FROM pair) GROUP BY ALL) p ON p.corpus = u.corpus AND p.origin = u.origin"))
def _c10(spark, d):
    fps = fingers_of(spark, d, PAIRED)
    pairs = pairs_of(spark, d, PAIRED)
    ends = pairs.select("corpus", "origin", F.col("a").alias("v")).unionByName(pairs.select("corpus", "origin", F.col("b").alias("v")))
    n = ends.groupBy("corpus", "origin").agg(F.countDistinct("v").alias("n"))
    total = fps.groupBy("corpus", "origin").agg(F.count("*").alias("n_units"))
    return total.join(n, ["corpus", "origin"], "left").select("corpus", "origin", "n_units", F.coalesce("n", F.lit(0)).alias("n_involved"), F.expr("(10000 * coalesce(n, 0)) div n_units").alias("involved_bp"))


#: Least edit distance that symbol counts allow, and a pruning rule by it.
_BAG = "greatest(" + ", ".join(f"list_sum([greatest(length(x.fp) * 0 + length({p}) - length(replace({p}, s, '')) - (length({q}) - length(replace({q}, s, ''))), 0) FOR s IN list_distinct(string_split({p}, ''))])" for p, q in (("x.fp", "y.fp"), ("y.fp", "x.fp"))) + ")"


def _ablation_sql() -> str:
    every = S.with_(S.pairs(["documents", "pages"], 70, None), "SELECT corpus, count(*) AS n_all FROM pair GROUP BY 1")
    parts = []
    for rule in ("none", "length", "attrs", "fp_len", "bag"):
        ctes = S.compared(["documents", "pages"], None if rule == "none" else "fp_len" if rule == "bag" else rule)
        keep = f"100 * (max_len - {_BAG}) >= 70 * max_len" if rule == "bag" else "true"
        body = f"""SELECT '{rule}' AS prune, t.corpus, count(*) AS n_compared, count(*) FILTER (WHERE sim) AS n_similar, any_value(n_all) - count(*) FILTER (WHERE sim) AS n_lost
          FROM (SELECT c.corpus, 100 * (max_len - dist) >= 70 * max_len AS sim FROM comp c JOIN finger x ON x.unit_id = c.a AND x.corpus = c.corpus AND x.origin = c.origin
            JOIN finger y ON y.unit_id = c.b AND y.corpus = c.corpus AND y.origin = c.origin WHERE {keep}) t JOIN ({every}) e ON e.corpus = t.corpus GROUP BY t.corpus"""
        parts.append(f"SELECT * FROM ({S.with_(ctes, body)})")
    return " UNION ALL ".join(parts)


@query("w24_prune_ablation", _ablation_sql())
def _w24(spark, d):
    """Pairs that each rule leaves to compare, counted without a row for each, and similar ones that it loses."""
    fps = fingers_of(spark, d, ["documents", "pages"])
    rules = ("none", "length", "attrs", "fp_len", "bag")
    similar = materialize(pairing.similar_by_rule(fps, rules), "similar-by-rule")
    out = []
    for rule in rules:
        part = pairing.left_counts(fps, rule).join(similar.select("corpus", "n_all", F.col(rule).alias("n_similar")), "corpus")
        out.append(part.select(F.lit(rule).alias("prune"), "corpus", "n_compared", "n_similar", (F.col("n_all") - F.col("n_similar")).alias("n_lost")))
    return union(out)


_LOSS = S.with_(S.compared(["documents", "pages"], None), """SELECT corpus, count(*) AS n_similar, count(*) FILTER (WHERE NOT kept) AS n_lost, (10000 * count(*) FILTER (WHERE NOT kept)) // count(*) AS loss_bp FROM (
  SELECT c.corpus, 10 * least(x.n_ops, y.n_ops) >= 7 * greatest(x.n_ops, y.n_ops) AS kept FROM comp c JOIN finger x ON x.unit_id = c.a AND x.corpus = c.corpus JOIN finger y ON y.unit_id = c.b AND y.corpus = c.corpus
  WHERE 100 * (max_len - dist) >= 70 * max_len) GROUP BY corpus""")


@query("c18_pruning_loss", _LOSS)
def _c18(spark, d):
    fps = fingers_of(spark, d, ["documents", "pages"])
    return calibration.pruning_loss(pairing.similar_pairs(fps, prune=None), pairing.similar_pairs(fps, how="band", prune="length"))


@query("c18_lsh_loss")
def _c18_lsh(spark, d):
    fps = fingers_of(spark, d, ["documents", "pages"])
    return calibration.pruning_loss(pairing.similar_pairs(fps, prune="length"), pairing.similar_pairs(fps, how="minhash", prune="length"))


_TRUTH = "SELECT c.*, x.tok AS tx, y.tok AS ty, levenshtein(x.tok, y.tok) AS full_dist, greatest(length(x.tok), length(y.tok)) AS full_len FROM comp c JOIN finger x ON x.unit_id = c.a AND x.origin = c.origin JOIN finger y ON y.unit_id = c.b AND y.origin = c.origin"


@query("w08_calibrate", S.with_(S.compared(["scripts_week"]), f"""SELECT bin, a, b, score_bp::BIGINT AS score_bp, ((10000 * (full_len - full_dist)) // full_len)::BIGINT AS true_bp FROM (
  SELECT *, least(score_bp // 1000, 9) * 10 AS bin, row_number() OVER (PARTITION BY least(score_bp // 1000, 9) ORDER BY md5(a || '|' || b), a, b) AS r FROM ({_TRUTH})) WHERE r <= 100"""))
def _w08(spark, d):
    pairs = pairing.sample_pairs(fingers_of(spark, d, ["scripts_week"]), 100)
    return calibration.sampled_truth(pairs, texts_of(spark, d, "scripts_week"), 100)


_SWEEP = S.with_(S.compared(["scripts_week"]), f"""SELECT t AS threshold, count(*) FILTER (WHERE p AND q) AS tp, count(*) FILTER (WHERE p AND NOT q) AS fp, count(*) FILTER (WHERE NOT p AND q) AS fn FROM (
  SELECT t, 100 * (max_len - dist) >= t * max_len AS p, 100 * (full_len - full_dist) >= 70 * full_len AS q FROM ({_TRUTH}), range(40, 100, 5) r(t)) GROUP BY t""")


@query("m31_adaptive_threshold", _SWEEP)
@query("w08_calibrate_sweep", _SWEEP)
def _m31(spark, d):
    fps = texts_of(spark, d, "scripts_week")
    return calibration.sweep(calibration.with_truth(pairing.scored(pairing.candidate_pairs(fps, "band", "length")), fps))


@query("m31_best_threshold", f"SELECT threshold, tp, fp, fn, (20000 * tp) // greatest(2 * tp + fp + fn, 1) AS f1_bp FROM ({_SWEEP}) ORDER BY f1_bp DESC, threshold LIMIT 1")
def _m31_best(spark, d):
    return calibration.best_threshold(_m31(spark, d))


def true_pairs(spark: SparkSession, d: str, c: str) -> DataFrame:
    """All pairs of units of which token sequences, operands erased, are 70 % alike; no pruning by fingerprint.

    A token is one symbol; the exact plan over chunks of symbols finds the pairs.
    """
    made = lambda: pairing.similar_pairs(calibration.token_fingers(texts_of(spark, d, c), CORPORA[c]), 70, True, "chunk", None)
    return shared_table(spark, d, "true-pairs", (c,), made)


@query("m31_calibrated")
def _m31_calibrated(spark, d):
    """Per corpus the threshold on fingerprint scores that agrees best with the truth on tokens."""
    out = []
    for c in PAIRED:
        scores = pairing.similar_pairs(fingers_of(spark, d, [c]), 40)
        swept = calibration.sweep_against(scores, true_pairs(spark, d, c))
        out.append(calibration.best_threshold(swept).select(F.lit(c).alias("corpus"), "*"))
    return union(out)


def _accuracy_sql(corpora: list[str]) -> str:
    parts = []
    for c in corpora:
        for m in ("block", "fixed", "random"):
            q = S.with_(S.compared([c], "length", method=m), f"SELECT 100 * (max_len - dist) >= 70 * max_len AS p, 100 * (full_len - full_dist) >= 70 * full_len AS q FROM ({_TRUTH})")
            parts.append(f"SELECT '{c}' AS corpus, '{m}' AS method, count(*) FILTER (WHERE p) AS n_pred, count(*) FILTER (WHERE q) AS n_true, count(*) FILTER (WHERE p AND q) AS n_both FROM ({q})")
    return f"SELECT *, CASE WHEN n_pred > 0 THEN (10000 * n_both) // n_pred END AS precision_bp, CASE WHEN n_true > 0 THEN (10000 * n_both) // n_true END AS recall_bp FROM ({' UNION ALL '.join(parts)})"


@query("c19_accuracy", _accuracy_sql(["scripts_week"]))
def _c19(spark, d):
    """Accuracy among compared pairs; w23 counts the true pairs that pruning loses too."""
    out = []
    for m in ("block", "fixed", "random"):
        fps = texts_of(spark, d, "scripts_week", method=m)
        part = calibration.accuracy(calibration.with_truth(pairing.scored(pairing.candidate_pairs(fps, "band", "length")), fps))
        out.append(part.select(F.lit("scripts_week").alias("corpus"), F.lit(m).alias("method"), "*"))
    return union(out)


#: Baseline: stages, cutting method and pruning rule.
BASELINES = {
    "block": (preprocess.STAGES, "block", "length"), "fixed": (preprocess.STAGES, "fixed", "length"), "random": (preprocess.STAGES, "random", "length"),
    "rolling": (preprocess.STAGES, "rolling", "length"), "no_prune": (preprocess.STAGES, "block", None),
    "no_erase": (("prefix", "trailer"), "block", "length"), "no_strip": (("operands",), "block", "length"),
}


@query("w23_baselines")
def _w23(spark, d):
    """Every baseline against all true pairs of units, by corpus, with its compression.

    Units of other stages are named by artifacts; a predicted pair counts for the
    units that hold these, and pairs within one unit are no prediction.  The whole
    hash pairs nothing but equal token strings, which are one unit.
    """
    out = []
    for c in PAIRED:
        truth = true_pairs(spark, d, c).select("origin", "a", "b")
        n_true = truth.agg(F.count("*").alias("n_true"))
        norm = prints_of(spark, d, c).select("origin", "token_hash", "artifact_id")
        held = norm.join(fingers_of(spark, d, [c]).select("origin", "token_hash", "unit_id"), ["origin", "token_hash"]).select("origin", "artifact_id", "unit_id")
        held = shared_table(spark, d, "held", (c,), lambda held=held: held)
        for name, (stages, method, prune) in BASELINES.items():
            kw = {} if method == "block" else {"method": method}
            fps = fingers_of(spark, d, [c], stages, **kw)
            pairs = pairing.similar_pairs(fps, prune=prune).select("origin", "a", "b")
            if stages != preprocess.STAGES:
                x, y = (held.select("origin", F.col("artifact_id").alias(s), F.col("unit_id").alias(f"u{s}")) for s in ("a", "b"))
                pairs = pairs.join(x, ["origin", "a"]).join(y, ["origin", "b"]).where("ua <> ub").select("origin", F.least("ua", "ub").alias("a"), F.greatest("ua", "ub").alias("b")).distinct()
            marked = pairs.join(truth.withColumn("hit", F.lit(1)), ["origin", "a", "b"], "left")
            n = marked.agg(F.count("*").alias("n_pred"), F.count("hit").alias("n_both"))
            size = fps.agg(F.coalesce(F.sum("fp_len"), F.lit(0)).cast("bigint").alias("symbols"), F.coalesce(F.sum("n_bytes"), F.lit(0)).cast("bigint").alias("bytes"))
            out.append(n.crossJoin(n_true).crossJoin(size).select(F.lit(c).alias("corpus"), F.lit(name).alias("method"), "*"))
        equal = n_true.select(F.lit(c).alias("corpus"), F.lit("whole_hash").alias("method"), F.lit(0).cast("bigint").alias("n_pred"), F.lit(0).cast("bigint").alias("n_both"), "n_true")
        sums = fingers_of(spark, d, [c]).agg(F.count("*").alias("symbols"), F.coalesce(F.sum("n_bytes"), F.lit(0)).cast("bigint").alias("bytes"))
        out.append(equal.crossJoin(sums))
    share = lambda of: F.when(F.col(of) > 0, F.expr(f"(10000 * n_both) div {of}"))
    return union(out).select("corpus", "method", "n_pred", "n_true", "n_both", share("n_pred").alias("precision_bp"), share("n_true").alias("recall_bp"), F.expr("(10000 * symbols) div greatest(bytes, 1)").alias("ratio_bp"))


# --- clusters -------------------------------------------------------------------------------


def _cluster_ctes(c: str) -> str:
    """pair, label, cl of one corpus; scripts need fingerprints of four symbols or more."""
    base = S.pairs([c], CLUSTERED[c])
    if c == "scripts_week":
        base = base.replace("pair AS MATERIALIZED (SELECT * FROM comp WHERE", f"pair AS MATERIALIZED (SELECT * FROM comp WHERE least(la, lb) >= {MIN_FP} AND")
    return f"{base},\n{S.components()},\ncl AS (SELECT v AS unit_id, l AS cluster_id FROM label)"


def cluster_parts(spark: SparkSession, d: str, c: str) -> tuple[DataFrame, DataFrame, DataFrame]:
    """(fingers, pairs, clusters) of one corpus at its threshold."""
    fps = fingers_of(spark, d, [c])
    pairs = pairs_of(spark, d, [c], CLUSTERED[c])
    if c == "scripts_week":
        pairs = pairs.where(F.least("la", "lb") >= MIN_FP)
    return fps, pairs, shared_table(spark, d, "clusters", (c, CLUSTERED[c]), lambda: homogeneity.clusters(pairs))


for _c in CLUSTERED:

    def _run(spark, d, c=_c):
        return cluster_parts(spark, d, c)[2]

    query(f"m41_components_{_c}", S.with_(_cluster_ctes(_c), "SELECT unit_id, cluster_id FROM cl"))(_run)

    def _run(spark, d, c=_c):
        fps, _, cl = cluster_parts(spark, d, c)
        return homogeneity.cluster_sizes(cl, fps)

    _sizes_sql = "SELECT cluster_id, count(*) AS n_units, sum(n_dup)::BIGINT AS n_artifacts FROM cl JOIN finger USING (unit_id) GROUP BY 1"
    query(f"w10_clusters_{_c}", S.with_(_cluster_ctes(_c), _sizes_sql))(_run)

    def _run(spark, d, c=_c):
        fps, pairs, cl = cluster_parts(spark, d, c)
        total = fps.agg(F.count("*").alias("n_units"))
        return cl.agg(F.countDistinct("cluster_id").alias("n_clusters"), F.count("*").alias("n_clustered")).join(total).select("n_clusters", "n_clustered", (F.col("n_units") - F.col("n_clustered")).alias("n_isolated"))

    query(f"c11_cluster_counts_{_c}", S.with_(_cluster_ctes(_c), "SELECT count(DISTINCT cluster_id) AS n_clusters, count(*) AS n_clustered, (SELECT count(*) FROM finger) - count(*) AS n_isolated FROM cl"))(_run)

_DOC = _cluster_ctes("documents")
_LABELLED = S.with_(_DOC, "SELECT unit_id, cluster_id FROM cl")


@query("m41_label_min", _LABELLED)
def _m41_min(spark, d):
    return graph.label_min(pairs_of(spark, d, ["documents"])).toDF("unit_id", "cluster_id")


@query("m41_driver_unionfind", _LABELLED)
def _m41_driver(spark, d):
    return graph.driver_components(pairs_of(spark, d, ["documents"])).toDF("unit_id", "cluster_id")


_SIZES = "sizes AS (SELECT cluster_id, count(*) AS n_units, sum(n_dup)::BIGINT AS n_artifacts FROM cl JOIN finger USING (unit_id) GROUP BY 1)"


@query("m42_isolated", S.with_(_DOC, "SELECT unit_id FROM finger WHERE unit_id NOT IN (SELECT unit_id FROM cl)"))
def _m42(spark, d):
    fps, pairs, _ = cluster_parts(spark, d, "documents")
    return homogeneity.isolated(fps, pairs).select("unit_id")


@query("m43_cluster_sizes", S.with_(f"{_DOC}, {_SIZES}", "SELECT * FROM sizes"))
def _m43(spark, d):
    fps, _, cl = cluster_parts(spark, d, "documents")
    return homogeneity.cluster_sizes(cl, fps)


def _sizes(spark, d, c="documents"):
    fps, _, cl = cluster_parts(spark, d, c)
    return homogeneity.cluster_sizes(cl, fps)


@query("m44_size_distribution", S.with_(f"{_DOC}, {_SIZES}", "SELECT group_size, n_groups, n_members, sum(n_members) OVER (ORDER BY group_size DESC)::BIGINT AS cum_members FROM (SELECT n_units AS group_size, count(*) AS n_groups, sum(n_units)::BIGINT AS n_members FROM sizes GROUP BY 1)"))
def _m44(spark, d):
    return homogeneity.size_histogram(_sizes(spark, d), "n_units")


def _share_sql(src: str, weight: str, pct: int) -> str:
    return f"SELECT '{weight}' AS weight, {pct}::BIGINT AS pct, max(k)::BIGINT AS n_top, (10000 * sum(CASE WHEN r <= k THEN {weight} ELSE 0 END)::BIGINT) // sum({weight})::BIGINT AS share_bp FROM (SELECT *, row_number() OVER (ORDER BY {weight} DESC) AS r, ({pct} * count(*) OVER () + 99) // 100 AS k FROM {src})"


_PARETO = " UNION ALL ".join(_share_sql("sizes", w, p) for w in ("n_units", "n_artifacts") for p in (1, 20))


@query("m45_pareto", S.with_(f"{_DOC}, {_SIZES}", _PARETO))
@query("w11_pareto", S.with_(f"{_DOC}, {_SIZES}", _PARETO))
@query("c12_top_share", S.with_(f"{_DOC}, {_SIZES}", _PARETO))
def _m45(spark, d):
    sizes = materialize(_sizes(spark, d), "sizes")
    parts = [homogeneity.top_share(sizes, p, w) for w in ("n_units", "n_artifacts") for p in (1, 20)]
    return parts[0].unionByName(parts[1]).unionByName(parts[2]).unionByName(parts[3])


@query("w11_pareto_groups", S.with_(S.units(["scripts"]), " UNION ALL ".join(_share_sql("unit", "n_dup", p) for p in (1, 20))))
def _w11g(spark, d):
    u = materialize(units_of(spark, d, ["scripts"]).select("token_hash", "n_dup"), "sizes")
    return homogeneity.top_share(u, 1, "n_dup").unionByName(homogeneity.top_share(u, 20, "n_dup"))


@query("m46_cdf", S.with_(S.units(["scripts"]), """SELECT group_size, ((10000 * sum(g) OVER w) // sum(g) OVER ())::BIGINT AS groups_bp, ((10000 * sum(m) OVER w) // sum(m) OVER ())::BIGINT AS members_bp
  FROM (SELECT n_dup AS group_size, count(*) AS g, sum(n_dup) AS m FROM unit GROUP BY 1) WINDOW w AS (ORDER BY group_size DESC)"""))
def _m46(spark, d):
    return homogeneity.size_cdf(units_of(spark, d, ["scripts"]), "n_dup")


@query("m47_top_k", S.with_(f"{_DOC}, {_SIZES}", "SELECT cluster_id, n_units, n_artifacts FROM sizes ORDER BY n_units DESC, cluster_id LIMIT 10"))
def _m47(spark, d):
    return _sizes(spark, d).orderBy(F.desc("n_units"), "cluster_id").limit(10)


def _label_case() -> str:
    return "CASE " + " ".join(f"WHEN regexp_matches(tok, '{p}') THEN '{n}'" for n, p in homogeneity.LABEL_RULES.items()) + " ELSE 'plain' END"


_LABELS = f"lab AS (SELECT cluster_id, first(label ORDER BY n DESC, label) AS label FROM (SELECT cluster_id, {_label_case()} AS label, count(*) AS n FROM cl JOIN finger USING (unit_id) GROUP BY ALL) GROUP BY 1)"


@query("m49_label_clusters", S.with_(f"{_DOC}, {_LABELS}", "SELECT * FROM lab"))
def _m49(spark, d):
    return homogeneity.label_clusters(cluster_parts(spark, d, "documents")[2], texts_of(spark, d, "documents"))


@query("w12_top15", S.with_(f"{_DOC}, {_LABELS}, osz AS (SELECT origin, cluster_id, count(*) AS n_units, sum(n_dup)::BIGINT AS n_artifacts FROM cl JOIN finger USING (unit_id) GROUP BY ALL)",
    "SELECT origin, r AS rank, cluster_id, n_units, n_artifacts, label FROM (SELECT *, row_number() OVER (PARTITION BY origin ORDER BY n_units DESC, cluster_id) AS r FROM osz) JOIN lab USING (cluster_id) WHERE r <= 15"))
def _w12(spark, d):
    fps, _, cl = cluster_parts(spark, d, "documents")
    top = homogeneity.top_groups(homogeneity.cluster_sizes(cl, fps, ("origin",)), "n_units", 15, ("origin",), "cluster_id")
    return top.join(homogeneity.label_clusters(cl, texts_of(spark, d, "documents")), "cluster_id").select("origin", "rank", "cluster_id", "n_units", "n_artifacts", "label")


_MEDOID = """SELECT cluster_id, first(unit_id ORDER BY s DESC, unit_id) AS template_unit, max(s) AS score_sum, any_value(n_units) AS n_members FROM (
  SELECT cl.cluster_id, cl.unit_id, sum(score_bp)::BIGINT AS s, any_value(t.n_units) AS n_units FROM cl JOIN (SELECT * FROM sizes ORDER BY n_units DESC, cluster_id LIMIT 100) t USING (cluster_id)
  JOIN (SELECT a AS unit_id, score_bp FROM pair UNION ALL SELECT b, score_bp FROM pair) e USING (unit_id) GROUP BY ALL) GROUP BY cluster_id"""


@query("m50_medoid_template", S.with_(f"{_DOC}, {_SIZES}", _MEDOID))
@query("w13_templates", S.with_(f"{_DOC}, {_SIZES}", _MEDOID))
def _m50(spark, d):
    fps, pairs, cl = cluster_parts(spark, d, "documents")
    return homogeneity.suggest_templates(cl, pairs, homogeneity.cluster_sizes(cl, fps))


_MEMBERS = "mem0 AS MATERIALIZED (SELECT DISTINCT n.bundle_id, u.unit_id FROM norm n JOIN unit u ON u.corpus = n.corpus AND u.origin = n.origin AND u.token_hash = n.token_hash)"
#: What is left of bundles: mem is mem0 without templates, units of their clusters, and units that are similar to one.
_ELIMINATION = f"""med AS MATERIALIZED ({_MEDOID}),
tmpl AS MATERIALIZED (SELECT template_unit AS unit_id FROM med WHERE n_members >= {homogeneity.TEMPLATE_UNITS} UNION SELECT unit_id FROM mem0 GROUP BY 1 HAVING count(*) >= {homogeneity.COMMON_BUNDLES}),
alike AS MATERIALIZED (SELECT unit_id FROM tmpl UNION SELECT unit_id FROM cl WHERE cluster_id IN (SELECT cluster_id FROM cl WHERE unit_id IN (SELECT unit_id FROM tmpl))
  UNION SELECT b FROM pair WHERE a IN (SELECT unit_id FROM tmpl) UNION SELECT a FROM pair WHERE b IN (SELECT unit_id FROM tmpl)),
mem AS MATERIALIZED (SELECT * FROM mem0 WHERE unit_id NOT IN (SELECT unit_id FROM alike))"""
_FUNCTIONAL = f"{_DOC}, {_SIZES}, {_MEMBERS}, {_ELIMINATION}"


def bundle_parts(spark: SparkSession, d: str, corpus: str) -> tuple[DataFrame, DataFrame]:
    """(members, bundles), templates included."""
    norm = prints_of(spark, d, corpus)
    units = fingers_of(spark, d, [corpus]).select("corpus", "origin", "token_hash", "unit_id")
    return shared_table(spark, d, "members", (corpus,), lambda: bundles.members(norm, units)), shared_table(spark, d, "bundles", (corpus,), lambda: bundles.bundle_table(norm))


def functional_parts(spark: SparkSession, d: str, corpus: str) -> tuple[DataFrame, DataFrame, DataFrame]:
    """(members without templates, bundles, similar pairs): what bundles are matched by."""
    fps, linked, cl = cluster_parts(spark, d, corpus)
    mem, bun = bundle_parts(spark, d, corpus)
    pairs = pairs_of(spark, d, [corpus])

    def left() -> DataFrame:
        catalogue = materialize(homogeneity.template_catalogue(homogeneity.suggest_templates(cl, linked, homogeneity.cluster_sizes(cl, fps)), mem), "templates")
        return homogeneity.drop_templates(mem, materialize(homogeneity.template_units(catalogue, cl, linked), "template-units"))

    return shared_table(spark, d, "functional", (corpus,), left), bun, pairs


@query("m51_template_filter", S.with_(_FUNCTIONAL, "SELECT bundle_id, unit_id FROM mem"))
def _m51(spark, d):
    return functional_parts(spark, d, "documents")[0]


@query("m71_template_elimination", S.with_(_FUNCTIONAL, """SELECT a.bundle_id, a.n AS n_units, coalesce(b.n, 0) AS n_left, b.n IS NULL AS emptied
  FROM (SELECT bundle_id, count(*) AS n FROM mem0 GROUP BY 1) a LEFT JOIN (SELECT bundle_id, count(*) AS n FROM mem GROUP BY 1) b USING (bundle_id)"""))
def _m71(spark, d):
    return homogeneity.elimination(bundle_parts(spark, d, "documents")[0], functional_parts(spark, d, "documents")[0])


@query("w13_templates_benchmark", S.with_(S.units(["documents"]), """SELECT item_id, count(u.unit_id) AS n_units, coalesce(sum(u.n_dup), 0)::BIGINT AS n_artifacts FROM benchmark b
  LEFT JOIN (SELECT u.unit_id, u.n_dup, a.payload FROM unit u JOIN art a ON a.artifact_id = u.unit_id) u ON b.text <> '' AND contains(u.payload, b.text) GROUP BY 1"""))
def _w13_benchmark(spark, d):
    """The given catalogue of passages: units and artifacts that hold each."""
    units, rep = document_payloads(spark, d)
    items = table(spark, d, "benchmark").select("item_id", "text")
    held = findings.passages_held(rep, items.select("text")).join(units.select("unit_id", "n_dup"), "unit_id")
    n = held.groupBy(F.col("passage").alias("text")).agg(F.count("*").alias("n_units"), F.sum("n_dup").cast("bigint").alias("n_artifacts"))
    return items.join(n, "text", "left").select("item_id", F.coalesce("n_units", F.lit(0)).alias("n_units"), F.coalesce("n_artifacts", F.lit(0)).alias("n_artifacts"))


@query("m52_normalized_sizes", S.with_(S.units(["scripts"]), "SELECT origin, token_hash, n_dup, (10000 * n_dup) // max(n_dup) OVER (PARTITION BY origin) AS norm_bp FROM unit"))
def _m52(spark, d):
    u = materialize(units_of(spark, d, ["scripts"]).select("origin", "token_hash", "n_dup"), "sizes")
    return homogeneity.normalize_sizes(u, "n_dup", ("origin",)).select("origin", "token_hash", "n_dup", "norm_bp")


# --- findings ---------------------------------------------------------------------------------


def document_payloads(spark: SparkSession, d: str) -> tuple[DataFrame, DataFrame]:
    """(units, payload of every artifact by the name that a unit of it would have) of documents: what is found there is joined with units, not the texts."""
    return fingers_of(spark, d, ["documents"]), payloads(spark, d, "documents").withColumnRenamed("artifact_id", "unit_id")


def finding_parts(spark: SparkSession, d: str) -> tuple[DataFrame, DataFrame]:
    """(units, findings) of documents."""
    units, rep = document_payloads(spark, d)

    def scanned() -> DataFrame:
        labels = table(spark, d, "labels").select(F.col("doc_id").cast("string").alias("unit_id"), "quality", "toxic").join(units.select("unit_id"), "unit_id", "left_semi")
        return findings.scan(rep, labels, table(spark, d, "benchmark").select("text")).join(units.select("unit_id"), "unit_id", "left_semi")

    return units, shared_table(spark, d, "findings", (), scanned)


_FOUND = f"{S.units(['documents'])}, {S.findings()}"


@query("m60_scan_units", S.with_(_FOUND, "SELECT unit_id, ftype, n::BIGINT AS n FROM found"))
def _m60(spark, d):
    return finding_parts(spark, d)[1]


@query("m61_inherit", S.with_(_FOUND, "SELECT n.artifact_id, ftype, f.n::BIGINT AS n FROM norm n JOIN unit u ON u.origin = n.origin AND u.token_hash = n.token_hash JOIN found f ON f.unit_id = u.unit_id"))
def _m61(spark, d):
    units, found = finding_parts(spark, d)
    return findings.inherit(found, norm_of(spark, d, ["documents"]), units)


_PREV = S.with_(_FOUND, """SELECT origin, count(*) AS n_units, count(*) FILTER (WHERE bad) AS n_vuln_units, sum(n_dup)::BIGINT AS n_artifacts, coalesce(sum(n_dup) FILTER (WHERE bad), 0)::BIGINT AS n_vuln_artifacts
  FROM (SELECT *, unit_id IN (SELECT unit_id FROM found) AS bad FROM unit) GROUP BY 1""")


@query("m62_prevalence", _PREV)
@query("w14_vuln_prevalence", _PREV)
@query("c13_prevalence", _PREV)
def _m62(spark, d):
    return findings.prevalence(*finding_parts(spark, d))


_DOC_PAIRS = f"{S.pairs(['documents'])}, {S.findings()}"


def _class_ctes(total: bool = False) -> str:
    n = "sum(n) OVER (PARTITION BY unit_id)" if total else "n"
    return f"""{_DOC_PAIRS}, fs AS MATERIALIZED (SELECT unit_id, string_agg(ftype || ':' || n::BIGINT::VARCHAR, ',' ORDER BY ftype) AS f, list(ftype) AS k FROM (SELECT unit_id, ftype, {n} AS n FROM found) GROUP BY 1),
cls AS MATERIALIZED (SELECT a, b, CASE WHEN x.f IS NULL AND y.f IS NULL THEN 'neither' WHEN x.f IS NULL OR y.f IS NULL THEN 'one' WHEN x.f = y.f THEN 'both_same' WHEN list_has_any(x.k, y.k) THEN 'overlap' ELSE 'disjoint' END AS cls,
  u.creator = w.creator AS same_author, u.first_seen_us AS sa, w.first_seen_us AS sb, x.f IS NOT NULL AS bad_a, y.f IS NOT NULL AS bad_b
  FROM pair p JOIN unit u ON u.unit_id = p.a JOIN unit w ON w.unit_id = p.b LEFT JOIN fs x ON x.unit_id = p.a LEFT JOIN fs y ON y.unit_id = p.b)"""


def classified(spark: SparkSession, d: str, count_mode: str = "per_type") -> DataFrame:
    units, found = finding_parts(spark, d)
    return findings.classified_pairs(pairs_of(spark, d, ["documents"]), units, found, count_mode)


for _mode in ("per_type", "total"):

    def _run(spark, d, m=_mode):
        return classified(spark, d, m).select("a", "b", "cls")

    query(f"m63_behaviour_{_mode}", S.with_(_class_ctes(_mode == "total"), "SELECT a, b, cls FROM cls"))(_run)


@query("m64_authorship", S.with_(_class_ctes(), "SELECT a, b, same_author FROM cls"))
def _m64(spark, d):
    return classified(spark, d).select("a", "b", "same_author")


@query("m64_authorship_any_overlap", S.with_(S.pairs(["documents"]), """SELECT a, b, EXISTS (SELECT 1 FROM norm x JOIN norm y ON x.creator = y.creator
  JOIN unit u ON u.origin = x.origin AND u.token_hash = x.token_hash JOIN unit w ON w.origin = y.origin AND w.token_hash = y.token_hash WHERE u.unit_id = pair.a AND w.unit_id = pair.b) AS same_author FROM pair"""))
def _m64_any(spark, d):
    """The other reading of authorship: some creator deployed instances of both units."""
    norm = prints_of(spark, d, "documents").select("origin", "token_hash", "creator")
    own = norm.join(fingers_of(spark, d, ["documents"]).select("origin", "token_hash", "unit_id"), ["origin", "token_hash"]).select("unit_id", "creator")
    return findings.shared_creators(pairs_of(spark, d, ["documents"]), own)


_TAB4 = S.with_(_class_ctes(), "SELECT same_author::VARCHAR AS same_author, " + ", ".join(f"count(*) FILTER (WHERE cls = '{c}') AS {c}" for c in findings.CLASSES) + " FROM cls GROUP BY ROLLUP (same_author)")


@query("m65_tab4", _TAB4)
@query("w15_vuln_pairs", _TAB4)
def _m65(spark, d):
    return findings.behaviour_table(classified(spark, d)).withColumn("same_author", F.col("same_author").cast("string"))


_CASE = S.with_(f"""{_DOC_PAIRS}, {S.components()}, cl AS (SELECT v AS unit_id, l AS cluster_id FROM label),
  f1 AS (SELECT cluster_id, count(*) AS n_units, first(unit_id ORDER BY coalesce(first_seen_us, {S.LATEST}), unit_id) AS unit_id FROM cl JOIN unit USING (unit_id) GROUP BY 1),
  kind AS (SELECT unit_id, min(ftype) AS ftype FROM found GROUP BY 1),
  pick AS (SELECT cluster_id, n_units, ftype FROM f1 JOIN kind USING (unit_id) ORDER BY n_units DESC, cluster_id LIMIT 1)""",
    "SELECT p.cluster_id, p.ftype, p.n_units, count(*) AS n_with, (10000 * count(*)) // any_value(p.n_units) AS share_bp FROM pick p JOIN cl ON cl.cluster_id = p.cluster_id JOIN found f ON f.unit_id = cl.unit_id AND f.ftype = p.ftype GROUP BY p.cluster_id, p.ftype, p.n_units")


@query("m66_case_cluster", _CASE)
@query("w16_case_study", _CASE)
def _m66(spark, d):
    units, found = finding_parts(spark, d)
    return findings.case_cluster(cluster_parts(spark, d, "documents")[2], units, found)


@query("m67_patch_direction", S.with_(_class_ctes(), "SELECT CASE WHEN CASE WHEN sa < sb THEN bad_a ELSE bad_b END THEN 'fixed_later' ELSE 'introduced_later' END AS direction, count(*) AS n_pairs FROM cls WHERE cls = 'one' AND sa <> sb GROUP BY 1"))
def _m67(spark, d):
    return findings.patch_direction(classified(spark, d))


@query("c14_same_vuln_share", S.with_(_class_ctes(), "SELECT count(*) AS n_pairs, (10000 * count(*) FILTER (WHERE cls = 'both_same')) // greatest(count(*), 1) AS same_bp FROM cls"))
def _c14(spark, d):
    return classified(spark, d).agg(F.count("*").alias("n_pairs"), F.count_if(F.col("cls") == "both_same").alias("s")).select("n_pairs", F.expr("(10000 * s) div greatest(n_pairs, 1)").alias("same_bp"))


@query("c15_cross_author", S.with_(_class_ctes(), "SELECT cls, count(*) AS n_pairs, (10000 * count(*) FILTER (WHERE NOT same_author)) // count(*) AS cross_bp FROM cls GROUP BY 1"))
def _c15(spark, d):
    return classified(spark, d).groupBy("cls").agg(F.count("*").alias("n_pairs"), F.count_if(~F.col("same_author")).alias("x")).select("cls", "n_pairs", F.expr("(10000 * x) div n_pairs").alias("cross_bp"))


# --- bundles ----------------------------------------------------------------------------------


_BUN = """bun AS MATERIALIZED (SELECT bundle_id, min(creator) AS owner, min(deployed_us) AS deployed_us, coalesce(sum(volume_milli), 0)::BIGINT AS volume_milli FROM norm GROUP BY 1)"""
_WEIGHTS = """siz AS MATERIALIZED (SELECT bundle_id, count(*) AS n FROM mem GROUP BY 1),
edge AS MATERIALIZED (SELECT a AS i, b AS j, score_bp AS w FROM pair UNION ALL SELECT b, a, score_bp FROM pair UNION ALL SELECT DISTINCT unit_id, unit_id, 10000 FROM mem),
wgt AS MATERIALIZED (SELECT x.bundle_id AS ua, y.bundle_id AS ub, e.i, e.j, e.w::BIGINT AS w FROM edge e JOIN mem x ON x.unit_id = e.i JOIN mem y ON y.unit_id = e.j JOIN bun p ON p.bundle_id = x.bundle_id JOIN bun q ON q.bundle_id = y.bundle_id
  WHERE x.bundle_id < y.bundle_id AND p.owner <> q.owner)"""
_DOC_BUNDLES = f"{_FUNCTIONAL}, {_BUN}, {_WEIGHTS}"
#: Optimal matching by enumeration: the smaller side's members in order, a mask of the other side's used ones, and the option to skip.
_MATCH = """side AS MATERIALIZED (SELECT ua, ub, CASE WHEN a.n <= b.n THEN i ELSE j END AS s, CASE WHEN a.n <= b.n THEN j ELSE i END AS l, w, a.n AS n_a, b.n AS n_b FROM wgt JOIN siz a ON a.bundle_id = ua JOIN siz b ON b.bundle_id = ub),
num AS MATERIALIZED (SELECT ua, ub, n_a, n_b, w, dense_rank() OVER (PARTITION BY ua, ub ORDER BY s) AS r, dense_rank() OVER (PARTITION BY ua, ub ORDER BY l) - 1 AS c FROM side),
opt AS MATERIALIZED (SELECT ua, ub, r, c, w FROM num UNION ALL SELECT DISTINCT ua, ub, r, -1, 0 FROM num),
walk(ua, ub, r, mask, total) AS (SELECT DISTINCT ua, ub, 0::BIGINT, 0::BIGINT, 0::BIGINT FROM num
  UNION SELECT k.ua, k.ub, o.r, CASE WHEN o.c < 0 THEN k.mask ELSE k.mask | (1::BIGINT << o.c) END, k.total + o.w FROM walk k JOIN opt o ON o.ua = k.ua AND o.ub = k.ub AND o.r = k.r + 1 WHERE o.c < 0 OR (k.mask & (1::BIGINT << o.c)) = 0),
best AS MATERIALIZED (SELECT k.ua, k.ub, max(total) AS total_bp, any_value(n_a) AS n_a, any_value(n_b) AS n_b FROM walk k JOIN (SELECT DISTINCT ua, ub, n_a, n_b FROM num) z ON z.ua = k.ua AND z.ub = k.ub GROUP BY k.ua, k.ub),
sim AS MATERIALIZED (SELECT ua, ub, n_a, n_b, total_bp, total_bp // n_a AS sim_ab_bp, total_bp // n_b AS sim_ba_bp, greatest(total_bp // n_a, total_bp // n_b) AS sim_bp FROM best)"""


@query("m70_bundle_members", S.with_(f"{S.units(['documents'])}, {_MEMBERS}", "SELECT bundle_id, unit_id FROM mem0"))
def _m70(spark, d):
    return bundle_parts(spark, d, "documents")[0]


def _weights(spark, d, corpus="documents"):
    return bundles.bipartite(*functional_parts(spark, d, corpus))


@query("m72_bundle_candidates", S.with_(_DOC_BUNDLES, "SELECT DISTINCT ua, ub FROM wgt"))
def _m72(spark, d):
    return _weights(spark, d).select("ua", "ub").distinct()


@query("m73_bipartite", S.with_(_DOC_BUNDLES, "SELECT ua, ub, i, j, w FROM wgt"))
def _m73(spark, d):
    return _weights(spark, d)


@query("m74_assignment", S.with_(f"{_DOC_BUNDLES}, {_MATCH}", "SELECT ua, ub, total_bp FROM best"))
def _m74(spark, d):
    mem = functional_parts(spark, d, "documents")[0]
    return bundles.match_bundles(bundles.bounded_pairs(_weights(spark, d), bundles.bundle_sizes(mem), 0)).select("ua", "ub", "total_bp")


@query("b09_greedy_match")
def _b09(spark, d):
    mem = functional_parts(spark, d, "documents")[0]
    w = materialize(bundles.bounded_pairs(materialize(_weights(spark, d), "edges"), bundles.bundle_sizes(mem), 0), "weights")
    best, quick = bundles.match_bundles(w), bundles.match_bundles(w, "greedy")
    both = best.select("ua", "ub", "total_bp").join(quick.select("ua", "ub", F.col("total_bp").alias("greedy_bp")), ["ua", "ub"])
    return both.agg(F.count("*").alias("n_pairs"), F.count_if(F.col("greedy_bp") < F.col("total_bp")).alias("n_worse"), F.sum("total_bp").alias("optimal_bp"), F.sum("greedy_bp").alias("greedy_bp"))


@query("m75_directional_sim", S.with_(f"{_DOC_BUNDLES}, {_MATCH}", "SELECT * FROM sim"))
def _m75(spark, d):
    return bundles.bundle_clones(*functional_parts(spark, d, "documents"), 0)


_CLONES = S.with_(f"{_DOC_BUNDLES}, {_MATCH}", "SELECT * FROM sim WHERE sim_bp >= 7000")


def clones_of(spark: SparkSession, d: str, corpus: str = "documents") -> tuple[DataFrame, DataFrame]:
    """(clone pairs, bundles), templates eliminated first."""
    mem, bun, pairs = functional_parts(spark, d, corpus)
    return shared_table(spark, d, "clones", (corpus,), lambda: bundles.bundle_clones(mem, bun, pairs)), bun


@query("m76_clone_pairs", _CLONES)
@query("w17_bundle_clones", _CLONES)
def _m76(spark, d):
    return clones_of(spark, d)[0]


@query("w17_bundle_clones_pages")
def _w17p(spark, d):
    return clones_of(spark, d, "pages")[0]


@query("w17_bundle_matches_pages")
def _w17m(spark, d):
    """Bundles of pages matched with templates left in, which their definition excludes: what elimination removes there."""
    mem, bun = bundle_parts(spark, d, "pages")
    return bundles.bundle_clones(mem, bun, pairs_of(spark, d, ["pages"]))


def _cc(base: str) -> str:
    return f"{base}, {_MATCH}, clone AS MATERIALIZED (SELECT * FROM sim WHERE sim_bp >= 7000), {S.components('clone', 'ua', 'ub', 'b')}, bcl AS MATERIALIZED (SELECT v AS bundle_id, l AS cluster_id FROM blabel)"


_ORIG = f"orig AS MATERIALIZED (SELECT cluster_id, first(bundle_id ORDER BY coalesce(deployed_us, {S.LATEST}), bundle_id) AS original FROM bcl JOIN bun USING (bundle_id) GROUP BY 1)"


def _impact_sql(base: str) -> str:
    return f"""{_cc(base)}, {_ORIG}, imp AS MATERIALIZED (SELECT *, CASE WHEN original_milli > 0 THEN (10000 * clone_milli) // original_milli END AS ratio_bp FROM (
  SELECT cluster_id, original, count(*) - 1 AS n_clones, sum(CASE WHEN bundle_id = original THEN volume_milli ELSE 0 END)::BIGINT AS original_milli, sum(CASE WHEN bundle_id = original THEN 0 ELSE volume_milli END)::BIGINT AS clone_milli
  FROM bcl JOIN bun USING (bundle_id) JOIN orig USING (cluster_id) GROUP BY ALL))"""


_CC, _IMPACT = _cc(_DOC_BUNDLES), _impact_sql(_DOC_BUNDLES)


@query("m77_clone_clusters", S.with_(_CC, "SELECT * FROM bcl"))
def _m77(spark, d):
    return bundles.clone_clusters(clones_of(spark, d)[0])


@query("m78_original", S.with_(f"{_CC}, {_ORIG}", "SELECT * FROM orig"))
def _m78(spark, d):
    clones, bun = clones_of(spark, d)
    return bundles.pick_originals(bundles.clone_clusters(clones), bun)


def _impact(spark, d):
    clones, bun = clones_of(spark, d)
    return bundles.volume_impact(bundles.clone_clusters(clones), bun)


@query("m79_impact", S.with_(_IMPACT, "SELECT * FROM imp"))
def _m79(spark, d):
    return _impact(spark, d)


_TOTALS_OF = """SELECT *, CASE WHEN original_milli > 0 THEN (10000 * clone_milli) // original_milli END AS ratio_bp FROM (SELECT count(*) AS n_clusters, count(DISTINCT original) AS n_originals, coalesce(sum(n_clones), 0)::BIGINT AS n_clones,
  coalesce(sum(original_milli), 0)::BIGINT AS original_milli, coalesce(sum(clone_milli), 0)::BIGINT AS clone_milli, count(*) FILTER (WHERE clone_milli > original_milli) AS n_exceeding FROM imp)"""
_TOTALS = S.with_(_IMPACT, _TOTALS_OF)


@query("w18_impact", _TOTALS)
@query("c17_volume_totals", _TOTALS)
def _w18(spark, d):
    return bundles.impact_totals(_impact(spark, d))


_TOP_OF = "SELECT * FROM imp ORDER BY n_clones DESC, cluster_id LIMIT 10"
_TOP_IMPACT = S.with_(_IMPACT, _TOP_OF)


@query("m80_top_impact", _TOP_IMPACT)
@query("w19_top10_impact", _TOP_IMPACT)
def _m80(spark, d):
    return _impact(spark, d).orderBy(F.desc("n_clones"), "cluster_id").limit(10)


@query("c16_bundle_counts", S.with_(_CC, "SELECT (SELECT count(*) FROM clone) AS n_pairs, count(*) AS n_bundles, count(DISTINCT cluster_id) AS n_clusters, count(*) - count(DISTINCT cluster_id) AS n_clones FROM bcl"))
def _c16(spark, d):
    clones, _ = clones_of(spark, d)
    n = clones.agg(F.count("*").alias("n_pairs"))
    cl = bundles.clone_clusters(clones).agg(F.count("*").alias("n_bundles"), F.countDistinct("cluster_id").alias("n_clusters"))
    return n.join(cl).select("n_pairs", "n_bundles", "n_clusters", (F.col("n_bundles") - F.col("n_clusters")).alias("n_clones"))


#: Every tenth bundle of documents deployed again by one other owner, later, with its last unit exchanged for a new one.
COPIER, LATER_US, COPY_STEP = "copier", 1_000_000, 10
_BLOCK = "CAST(split_part(bundle_id, '/', 2) AS BIGINT)"
_COPIED = f"{_BLOCK} % {COPY_STEP} = 0"
_PLANTED = f"""{_FUNCTIONAL.replace("mem AS MATERIALIZED", "mem1 AS MATERIALIZED")}, {_BUN.replace("bun AS MATERIALIZED", "bun1 AS MATERIALIZED")},
mem AS MATERIALIZED (SELECT * FROM mem1 UNION ALL SELECT 'copy/' || bundle_id, CASE WHEN unit_id = max(unit_id) OVER (PARTITION BY bundle_id) THEN 'new/' || bundle_id ELSE unit_id END FROM mem1 WHERE {_COPIED}),
bun AS MATERIALIZED (SELECT * FROM bun1 UNION ALL SELECT 'copy/' || bundle_id, '{COPIER}', deployed_us + {LATER_US}, volume_milli * (({_BLOCK} // {COPY_STEP}) % 4) // 2 FROM bun1 WHERE {_COPIED}), {_WEIGHTS}"""


def planted_parts(spark: SparkSession, d: str) -> tuple[DataFrame, DataFrame, DataFrame]:
    """As :func:`functional_parts` of documents, with planted clones: the given tables hold no bundle clone.

    A copy of n units keeps n - 1, so copies of four units or more are clones at 70 and
    smaller ones are not.  Its volume is 0, 1/2, 1 or 3/2 times that of its original.
    """
    mem, bun, pairs = functional_parts(spark, d, "documents")
    block = F.split_part("bundle_id", F.lit("/"), F.lit(2)).cast("bigint")
    last = mem.groupBy("bundle_id").agg(F.max("unit_id").alias("last"))
    copied = mem.where(block % COPY_STEP == 0).join(last, "bundle_id")
    name = F.concat(F.lit("copy/"), "bundle_id")
    unit = F.when(F.col("unit_id") == F.col("last"), F.concat(F.lit("new/"), "bundle_id")).otherwise(F.col("unit_id"))
    again = copied.select(name.alias("bundle_id"), unit.alias("unit_id"))
    times = F.pmod(F.floor(block / COPY_STEP), F.lit(4))
    deployed = bun.where(block % COPY_STEP == 0).withColumn("times", times).select(
        name.alias("bundle_id"), F.lit(COPIER).alias("owner"), (F.col("deployed_us") + LATER_US).alias("deployed_us"), F.expr("(volume_milli * times) div 2").alias("volume_milli")
    )
    return mem.unionByName(again), bun.unionByName(deployed), pairs


def planted_clones(spark: SparkSession, d: str) -> tuple[DataFrame, DataFrame]:
    mem, bun, pairs = planted_parts(spark, d)
    return shared_table(spark, d, "planted-clones", (), lambda: bundles.bundle_clones(mem, bun, pairs)), bun


def _planted_impact(spark, d):
    clones, bun = planted_clones(spark, d)
    return bundles.volume_impact(bundles.clone_clusters(clones), bun)


@query("w17_planted_clones", S.with_(f"{_PLANTED}, {_MATCH}", "SELECT * FROM sim WHERE sim_bp >= 7000"))
def _w17x(spark, d):
    return planted_clones(spark, d)[0]


@query("c16_planted_recall", S.with_(f"{_PLANTED}, {_MATCH}", """SELECT n_units, count(*) AS n_planted, count(s.ua) AS n_found FROM (SELECT bundle_id, count(*) AS n_units FROM mem WHERE starts_with(bundle_id, 'copy/') GROUP BY 1) p
  LEFT JOIN (SELECT ua, ub FROM sim WHERE sim_bp >= 7000) s ON s.ua = p.bundle_id AND 'copy/' || s.ub = p.bundle_id GROUP BY 1"""))
def _c16x(spark, d):
    """Planted copies by size, and how many of them are found as clones of their original."""
    copies = planted_parts(spark, d)[0].where(F.col("bundle_id").startswith("copy/")).groupBy(F.col("bundle_id").alias("ua")).agg(F.count("*").alias("n_units"))
    found = planted_clones(spark, d)[0].where(F.col("ua") == F.concat(F.lit("copy/"), "ub")).select("ua", F.lit(1).alias("hit"))
    return copies.join(found, "ua", "left").groupBy("n_units").agg(F.count("*").alias("n_planted"), F.count("hit").alias("n_found"))


@query("w18_planted_impact", S.with_(_impact_sql(_PLANTED), _TOTALS_OF))
def _w18x(spark, d):
    return bundles.impact_totals(_planted_impact(spark, d))


@query("w19_planted_top10", S.with_(_impact_sql(_PLANTED), _TOP_OF))
def _w19x(spark, d):
    return _planted_impact(spark, d).orderBy(F.desc("n_clones"), "cluster_id").limit(10)


# --- literal examples -------------------------------------------------------------------------

#: A program of 25 blocks, and a version in which a check of three blocks was edited. Fixed values.
_BASE = [f"5b60{i:02x}{'01' * (i % 5 + 1)}56" for i in range(1, 26)]
_EDIT = [*_BASE[:10], "5b60aa0203040557", "5b60ab0304050657", "5b60ac04050607fd", *_BASE[13:]]
WORKED = {"a": "".join(_BASE), "b": "".join(_EDIT)}


@query("w20_worked_example", S.with_(f"{_fixture_sql(WORKED)}, f AS ({_vm_fp_sql('prog')})", "SELECT x.fp AS fp_a, y.fp AS fp_b, levenshtein(x.fp, y.fp) AS dist, greatest(length(x.fp), length(y.fp)) AS max_len, (10000 * (greatest(length(x.fp), length(y.fp)) - levenshtein(x.fp, y.fp))) // greatest(length(x.fp), length(y.fp)) AS score_bp FROM f x, f y WHERE x.name = 'a' AND y.name = 'b'"))
def _w20(spark, d):
    fps = _vm_fps(spark, WORKED)
    a, b = fps.where("name = 'a'").select(F.col("fp").alias("fp_a")), fps.where("name = 'b'").select(F.col("fp").alias("fp_b"))
    both = a.join(b).withColumn("dist", F.levenshtein("fp_a", "fp_b").cast("bigint")).withColumn("max_len", F.greatest(F.length("fp_a"), F.length("fp_b")).cast("bigint"))
    return both.withColumn("score_bp", pairing.score_bp(F.col("dist"), F.col("max_len")))


#: A program with a flawed block, and a copy with other constants and one more function. Fixed values.
MOTIVE = {"original": "6080604052600a57" + "5b6005600660075603fd" + "5b61010100", "copy": "6080604052600b57" + "5b6009600860075603fd" + "5b610202600457" + "5b61030300"}
_FLAW = "5b60606056"


@query("w22_motivating", S.with_(f"{_fixture_sql(MOTIVE)}, f AS ({_vm_fp_sql('prog')})", f"SELECT x.name AS original, y.name AS copy, len(list_intersect(x.pieces, y.pieces)) AS n_shared_pieces, list_contains(x.pieces, '{_FLAW}') AND list_contains(y.pieces, '{_FLAW}') AS flawed_piece_kept FROM f x, f y WHERE x.name = 'original' AND y.name = 'copy'"))
def _w22(spark, d):
    f = _vm_fps(spark, MOTIVE)
    x, y = f.where("name = 'original'").select(F.col("name").alias("original"), F.col("pieces").alias("p")), f.where("name = 'copy'").select(F.col("name").alias("copy"), F.col("pieces").alias("q"))
    kept = F.array_contains("p", _FLAW) & F.array_contains("q", _FLAW)
    return x.join(y).select("original", "copy", F.size(F.array_intersect("p", "q")).cast("bigint").alias("n_shared_pieces"), kept.alias("flawed_piece_kept"))


@query("m08_stage_identity", S.with_(S.units(DUPES), "SELECT corpus, origin, count(*) AS n_units, sum(n_dup)::BIGINT AS n_artifacts, sum(n_runtime)::BIGINT AS n_runtimes FROM unit GROUP BY ALL"))
def _identity(spark, d):
    return preprocess.units(norm_of(spark, d, DUPES)).groupBy("corpus", "origin").agg(F.count("*").alias("n_units"), F.sum("n_dup").cast("bigint").alias("n_artifacts"), F.sum("n_runtime").cast("bigint").alias("n_runtimes"))
