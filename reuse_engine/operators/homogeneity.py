"""Clusters of units, their sizes, concentration measures and templates."""

from __future__ import annotations

from pyspark.sql import DataFrame, Window
from pyspark.sql import functions as F

from reuse_engine.graph import connected_components
from reuse_engine.storage import few_broadcast


def similarity_graph(pairs: DataFrame, threshold: int = 70) -> DataFrame:
    """Undirected edges with weight."""
    return pairs.where(F.col("score_bp") >= threshold * 100).select("a", "b", "score_bp")


def clusters(pairs: DataFrame, label: str = "clusters") -> DataFrame:
    """(unit_id, cluster_id): components of two or more units, named by the least."""
    return connected_components(pairs.select("a", "b"), label=label).toDF("unit_id", "cluster_id")


def isolated(units: DataFrame, pairs: DataFrame) -> DataFrame:
    ends = pairs.select(F.col("a").alias("unit_id")).unionByName(pairs.select(F.col("b").alias("unit_id"))).distinct()
    return units.join(ends, "unit_id", "left_anti")


def cluster_sizes(cl: DataFrame, units: DataFrame, extra: tuple[str, ...] = ()) -> DataFrame:
    return cl.join(units, "unit_id").groupBy(*extra, "cluster_id").agg(F.count("*").alias("n_units"), F.sum("n_dup").cast("bigint").alias("n_artifacts"))


def size_histogram(sizes: DataFrame, by: str = "n_artifacts", keys: tuple[str, ...] = ()) -> DataFrame:
    """Groups and members per size, with the running total of members from the largest size down."""
    counts = sizes.groupBy(*keys, F.col(by).alias("group_size")).agg(F.count("*").alias("n_groups"), F.sum(by).cast("bigint").alias("n_members"))
    order = Window.partitionBy(*keys).orderBy(F.desc("group_size")).rowsBetween(Window.unboundedPreceding, 0)
    return counts.withColumn("cum_members", F.sum("n_members").over(order))


def top_share(sizes: DataFrame, percent: int, weight: str, keys: tuple[str, ...] = ()) -> DataFrame:
    """Share of all members that the top ``percent`` of groups hold, in basis points.

    Works on the histogram of sizes: the groups of one size are equal, so the cut
    takes a part of one size's groups at most, and no window spans all groups.
    """
    hist = sizes.groupBy(*keys, F.col(weight).alias("size")).agg(F.count("*").alias("g"))
    down = Window.partitionBy(*keys).orderBy(F.desc("size")).rowsBetween(Window.unboundedPreceding, 0)
    whole = Window.partitionBy(*keys)
    ranked = hist.withColumn("upto", F.sum("g").over(down)).withColumn("all_g", F.sum("g").over(whole)).withColumn("total", F.sum(F.col("g") * F.col("size")).over(whole))
    n_top = F.expr(f"(all_g * {percent} + 99) div 100")
    taken = F.greatest(F.least(F.col("g"), n_top - (F.col("upto") - F.col("g"))), F.lit(0))
    return ranked.groupBy(*keys).agg(
        F.max(n_top).alias("n_top"), F.sum(taken * F.col("size")).cast("bigint").alias("held"), F.max("total").cast("bigint").alias("total")
    ).select(*keys, F.lit(weight).alias("weight"), F.lit(percent).cast("bigint").alias("pct"), "n_top", F.expr("(10000 * held) div total").alias("share_bp"))


def size_cdf(sizes: DataFrame, by: str = "n_artifacts") -> DataFrame:
    """Cumulative share of members against the share of groups, from the largest down, per size."""
    hist = size_histogram(sizes, by)
    down = Window.orderBy(F.desc("group_size")).rowsBetween(Window.unboundedPreceding, 0)  # one row per distinct size
    cum = hist.withColumn("cum_groups", F.sum("n_groups").over(down))
    total = hist.agg(F.sum("n_groups").alias("g"), F.sum("n_members").alias("m"))
    return cum.join(F.broadcast(total)).select(
        "group_size", F.expr("(10000 * cum_groups) div g").alias("groups_bp"), F.expr("(10000 * cum_members) div m").alias("members_bp")
    )


def normalize_sizes(sizes: DataFrame, by: str, keys: tuple[str, ...]) -> DataFrame:
    """Size as a share of the largest of its key, in basis points."""
    most = sizes.groupBy(*keys).agg(F.max(by).alias("most"))
    return sizes.join(F.broadcast(most), list(keys)).withColumn("norm_bp", F.expr(f"(10000 * {by}) div most")).drop("most")


def top_groups(sizes: DataFrame, by: str, k: int, keys: tuple[str, ...], tie: str) -> DataFrame:
    """The k largest per key; Spark prunes each task to k rows before the exchange."""
    order = Window.partitionBy(*keys).orderBy(F.desc(by), tie)
    return sizes.withColumn("rank", F.row_number().over(order).cast("bigint")).where(F.col("rank") <= k)


def duplication_metrics(norm: DataFrame, by: str, stage: str) -> DataFrame:
    """Share of artifacts in groups of two or more, per corpus and origin."""
    groups = norm.groupBy("corpus", "origin", by).agg(F.count("*").alias("n"))
    return groups.groupBy("corpus", "origin").agg(
        F.sum("n").cast("bigint").alias("n_artifacts"), F.sum(F.when(F.col("n") >= 2, F.col("n")).otherwise(0)).cast("bigint").alias("n_dup")
    ).select("corpus", "origin", F.lit(stage).alias("stage"), F.expr("(10000 * n_dup) div n_artifacts").alias("dup_share_bp"))


#: Label: words that vote for it. They stand for the manual reading of clusters.
LABEL_RULES = {"licence": "licen[cs]e|rights", "symbols": "[#$%&]{3}", "shout": "!!", "menu": "[|]"}


def label_clusters(cl: DataFrame, units: DataFrame, rules: dict[str, str] | None = None) -> DataFrame:
    """Most voted label of a cluster's units; ties go to the first by name, no vote to ``plain``."""
    label = F.lit("plain")
    for name, pattern in reversed(list((rules or LABEL_RULES).items())):
        label = F.when(F.col("tok").rlike(pattern), F.lit(name)).otherwise(label)
    votes = cl.join(units, "unit_id").groupBy("cluster_id", label.alias("label")).agg(F.count("*").alias("n"))
    return votes.groupBy("cluster_id").agg(F.min(F.struct((-F.col("n")).alias("n"), "label"))["label"].alias("label"))


def suggest_templates(cl: DataFrame, pairs: DataFrame, sizes: DataFrame, top: int = 100) -> DataFrame:
    """Per cluster among the ``top`` largest: the unit with the largest summed score."""
    best = sizes.orderBy(F.desc("n_units"), "cluster_id").limit(top).select("cluster_id", F.col("n_units").alias("n_members"))
    ends = pairs.select(F.col("a").alias("unit_id"), "score_bp").unionByName(pairs.select(F.col("b").alias("unit_id"), "score_bp"))
    sums = ends.join(cl, "unit_id").join(F.broadcast(best), "cluster_id").groupBy("cluster_id", "unit_id").agg(F.sum("score_bp").cast("bigint").alias("score_sum"), F.max("n_members").alias("n_members"))
    pick = sums.groupBy("cluster_id").agg(F.min(F.struct((-F.col("score_sum")).alias("s"), "unit_id", "n_members")).alias("p"))
    return pick.select("cluster_id", F.col("p.unit_id").alias("template_unit"), (-F.col("p.s")).alias("score_sum"), F.col("p.n_members").alias("n_members"))


#: Least units of a cluster that a template stands for, and least bundles that make a unit common.
TEMPLATE_UNITS, COMMON_BUNDLES = 3, 20


def template_catalogue(suggested: DataFrame, members: DataFrame) -> DataFrame:
    """(unit_id): suggested templates of clusters of ``TEMPLATE_UNITS`` or more, and units that ``COMMON_BUNDLES`` or more bundles hold."""
    common = members.groupBy("unit_id").agg(F.count("*").alias("n")).where(F.col("n") >= COMMON_BUNDLES).select("unit_id")
    return suggested.where(F.col("n_members") >= TEMPLATE_UNITS).select(F.col("template_unit").alias("unit_id")).union(common).distinct()


def template_units(catalogue: DataFrame, cl: DataFrame, pairs: DataFrame) -> DataFrame:
    """(unit_id): templates, units of their clusters, and units of a similar pair with one."""
    listed = few_broadcast(catalogue)
    mates = cl.join(cl.join(listed, "unit_id", "left_semi").select("cluster_id").distinct(), "cluster_id", "left_semi").select("unit_id")
    similar = pairs.join(listed.withColumnRenamed("unit_id", "a"), "a", "left_semi").select(F.col("b").alias("unit_id"))
    similar = similar.union(pairs.join(listed.withColumnRenamed("unit_id", "b"), "b", "left_semi").select("a"))
    return catalogue.union(mates).union(similar).distinct()


def drop_templates(members: DataFrame, templates: DataFrame) -> DataFrame:
    """Members whose unit is not among ``templates`` (unit_id); a bundle of nothing else is gone."""
    return members.join(few_broadcast(templates), "unit_id", "left_anti").select("bundle_id", "unit_id")


def elimination(members: DataFrame, left: DataFrame) -> DataFrame:
    """(bundle_id, n_units, n_left, emptied) of every bundle."""
    n = members.groupBy("bundle_id").agg(F.count("*").alias("n_units")).join(left.groupBy("bundle_id").agg(F.count("*").alias("k")), "bundle_id", "left")
    return n.select("bundle_id", "n_units", F.coalesce("k", F.lit(0)).alias("n_left"), F.col("k").isNull().alias("emptied"))
