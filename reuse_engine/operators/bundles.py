"""Clones among applications: bundles of programs matched by maximum weight."""

from __future__ import annotations

import numpy as np
import pandas as pd
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from reuse_engine.graph import connected_components
from reuse_engine.operators import assignment
from reuse_engine.storage import materialize

BUNDLE_THRESHOLD = 70
FULL_BP = 10_000


def members(norm: DataFrame, units: DataFrame) -> DataFrame:
    """(bundle_id, unit_id) of every bundle, each unit once."""
    named = norm.select("bundle_id", "corpus", "origin", "token_hash").join(units.select("corpus", "origin", "token_hash", "unit_id"), ["corpus", "origin", "token_hash"])
    return named.select("bundle_id", "unit_id").distinct()


def bundle_table(norm: DataFrame) -> DataFrame:
    """(bundle_id, owner, deployed_us, volume_milli)."""
    return norm.groupBy("bundle_id").agg(
        F.min("creator").alias("owner"), F.min("deployed_us").alias("deployed_us"), F.coalesce(F.sum("volume_milli"), F.lit(0)).cast("bigint").alias("volume_milli")
    )


def _edges(mem: DataFrame, pairs: DataFrame) -> DataFrame:
    """(i, j, w) in both directions over units, equal units included.

    Only units that occur in bundles are joined; the weight of equal units is full.
    """
    both = pairs.select(F.col("a").alias("i"), F.col("b").alias("j"), F.col("score_bp").alias("w")).unionByName(
        pairs.select(F.col("b").alias("i"), F.col("a").alias("j"), F.col("score_bp").alias("w"))
    )
    same = mem.select(F.col("unit_id").alias("i")).distinct().select("i", F.col("i").alias("j"), F.lit(FULL_BP).cast("bigint").alias("w"))
    return both.unionByName(same)


def bipartite(mem: DataFrame, bundles: DataFrame, pairs: DataFrame, min_edge: int = 0) -> DataFrame:
    """(ua, ub, i, j, w) for bundles of different owners with an edge, ua < ub."""
    owned = mem.join(bundles.select("bundle_id", "owner"), "bundle_id")
    left = owned.select(F.col("bundle_id").alias("ua"), F.col("owner").alias("oa"), F.col("unit_id").alias("i"))
    right = owned.select(F.col("bundle_id").alias("ub"), F.col("owner").alias("ob"), F.col("unit_id").alias("j"))
    met = _edges(mem, pairs).where(F.col("w") >= min_edge).join(left, "i").join(right, "j")
    return met.where("ua < ub and oa <> ob").select("ua", "ub", "i", "j", "w")


def bounded_pairs(weights: DataFrame, sizes: DataFrame, threshold: int = BUNDLE_THRESHOLD) -> DataFrame:
    """Weight rows of bundle pairs whose upper bound reaches the threshold.

    No matching exceeds the sum of the row maxima of either side.
    """
    rows = weights.groupBy("ua", "ub", "i").agg(F.max("w").alias("m")).groupBy("ua", "ub").agg(F.sum("m").alias("top_a"))
    cols = weights.groupBy("ua", "ub", "j").agg(F.max("w").alias("m")).groupBy("ua", "ub").agg(F.sum("m").alias("top_b"))
    sized = rows.join(cols, ["ua", "ub"]).join(sizes.toDF("ua", "n_a"), "ua").join(sizes.toDF("ub", "n_b"), "ub")
    keep = sized.where(F.least("top_a", "top_b") >= threshold * 100 * F.least("n_a", "n_b"))
    return weights.join(keep.select("ua", "ub", "n_a", "n_b"), ["ua", "ub"])


def _solve(algo: str):
    solve = assignment.max_weight if algo == "optimal" else assignment.greedy

    def run(pdf: pd.DataFrame) -> pd.DataFrame:
        i, rows = pd.factorize(pdf["i"], sort=True)
        j, cols = pd.factorize(pdf["j"], sort=True)
        w = np.zeros((len(rows), len(cols)), np.int64)
        w[i, j] = pdf["w"].to_numpy()
        total, matched = solve(w)
        return pd.DataFrame({"ua": [pdf["ua"].iloc[0]], "ub": [pdf["ub"].iloc[0]], "n_a": [pdf["n_a"].iloc[0]], "n_b": [pdf["n_b"].iloc[0]], "total_bp": [total], "matched": [len(matched)]})

    return run


def match_bundles(weights: DataFrame, algo: str = "optimal") -> DataFrame:
    """(ua, ub, n_a, n_b, total_bp, matched); one Arrow group per bundle pair with a choice.

    Where no unit of either side has two edges there is none, and the sum of all edges is the
    best total of any algorithm.
    """
    weights = materialize(weights, "weights")
    sums = weights.groupBy("ua", "ub", "n_a", "n_b").agg(
        F.count("*").alias("n"), F.countDistinct("i").alias("n_i"), F.countDistinct("j").alias("n_j"), F.sum("w").cast("bigint").alias("total_bp"), F.count_if(F.col("w") > 0).alias("matched")
    )
    sums = materialize(sums, "weight-sums")
    free = F.expr("n = n_i and n = n_j")
    chosen = weights.join(sums.where(~free).select("ua", "ub"), ["ua", "ub"], "left_semi")
    solved = chosen.groupBy("ua", "ub").applyInPandas(_solve(algo), "ua string, ub string, n_a long, n_b long, total_bp long, matched long")
    return sums.where(free).select("ua", "ub", "n_a", "n_b", "total_bp", "matched").unionByName(solved)


def bundle_sizes(mem: DataFrame) -> DataFrame:
    return mem.groupBy("bundle_id").agg(F.count("*").alias("n"))


def bundle_similarity(matched: DataFrame) -> DataFrame:
    """Directional shares of the own size; the larger one counts."""
    d = matched.withColumn("sim_ab_bp", F.expr("total_bp div n_a")).withColumn("sim_ba_bp", F.expr("total_bp div n_b"))
    return d.withColumn("sim_bp", F.greatest("sim_ab_bp", "sim_ba_bp")).select("ua", "ub", "n_a", "n_b", "total_bp", "sim_ab_bp", "sim_ba_bp", "sim_bp")


def bundle_clones(mem: DataFrame, bundles: DataFrame, pairs: DataFrame, threshold: int = BUNDLE_THRESHOLD, algo: str = "optimal") -> DataFrame:
    weights = bounded_pairs(materialize(bipartite(mem, bundles, pairs), "edges"), bundle_sizes(mem), threshold)
    return bundle_similarity(match_bundles(weights, algo)).where(F.col("sim_bp") >= threshold * 100)


def clone_clusters(clones: DataFrame) -> DataFrame:
    return connected_components(clones.select(F.col("ua").alias("a"), F.col("ub").alias("b")), label="bundles").toDF("bundle_id", "cluster_id")


def pick_originals(cl: DataFrame, bundles: DataFrame) -> DataFrame:
    """Earliest bundle of each cluster; unknown times come last, ties go by name."""
    aged = cl.join(bundles, "bundle_id")
    return aged.groupBy("cluster_id").agg(F.min(F.struct(F.coalesce("deployed_us", F.lit(1 << 62)).alias("us"), "bundle_id"))["bundle_id"].alias("original"))


def volume_impact(cl: DataFrame, bundles: DataFrame) -> DataFrame:
    """Per cluster: original, clones, and the volumes of both."""
    first = pick_originals(cl, bundles)
    rows = cl.join(bundles.select("bundle_id", "volume_milli"), "bundle_id").join(first, "cluster_id")
    is_first = F.col("bundle_id") == F.col("original")
    out = rows.groupBy("cluster_id", "original").agg(
        (F.count("*") - 1).alias("n_clones"),
        F.sum(F.when(is_first, F.col("volume_milli")).otherwise(0)).cast("bigint").alias("original_milli"),
        F.sum(F.when(is_first, 0).otherwise(F.col("volume_milli"))).cast("bigint").alias("clone_milli"),
    )
    return out.withColumn("ratio_bp", F.when(F.col("original_milli") > 0, F.expr("(10000 * clone_milli) div original_milli")))


def impact_totals(impact: DataFrame) -> DataFrame:
    sums = impact.agg(
        F.count("*").alias("n_clusters"), F.countDistinct("original").alias("n_originals"), F.coalesce(F.sum("n_clones"), F.lit(0)).cast("bigint").alias("n_clones"),
        F.coalesce(F.sum("original_milli"), F.lit(0)).cast("bigint").alias("original_milli"), F.coalesce(F.sum("clone_milli"), F.lit(0)).cast("bigint").alias("clone_milli"),
        F.count_if(F.col("clone_milli") > F.col("original_milli")).alias("n_exceeding"),
    )
    return sums.withColumn("ratio_bp", F.when(F.col("original_milli") > 0, F.expr("(10000 * clone_milli) div original_milli")))

