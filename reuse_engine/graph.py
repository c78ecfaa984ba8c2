"""Connected components over edge tables of any size.

Labels are contracted by alternating two local rewrites of the edge table
(every vertex hands its larger, then its smaller neighbours to the least vertex
it knows).  Each is one grouped pass, so no vertex's neighbourhood is ever
collected, and the number of rounds grows with the logarithm of the diameter.
Each round is written to the shared folder, which cuts the lineage.
"""

from __future__ import annotations

from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from reuse_engine.storage import discard, materialize

MAX_ROUNDS = 60


def _ordered(edges: DataFrame, u: str, v: str) -> DataFrame:
    """Distinct edges as (hi, lo) with lo < hi."""
    return (
        edges.select(F.greatest(u, v).alias("hi"), F.least(u, v).alias("lo"))
        .where(F.col("hi") != F.col("lo"))
        .distinct()
    )


def _large_star(edges: DataFrame) -> DataFrame:
    both = edges.select(F.col("hi").alias("v"), F.col("lo").alias("w")).unionByName(
        edges.select(F.col("lo").alias("v"), F.col("hi").alias("w"))
    )
    least = edges.groupBy(F.col("hi").alias("v")).agg(F.min("lo").alias("m"))
    joined = both.join(least, "v", "left").withColumn("m", F.coalesce("m", "v"))
    return joined.where(F.col("w") > F.col("v")).select(F.col("w").alias("hi"), F.col("m").alias("lo")).distinct()


def _small_star(edges: DataFrame) -> DataFrame:
    least = edges.groupBy("hi").agg(F.min("lo").alias("m"))
    joined = edges.join(least, "hi")
    moved = joined.where(F.col("lo") != F.col("m")).select(F.col("lo").alias("hi"), F.col("m").alias("lo"))
    kept = least.select("hi", F.col("m").alias("lo"))
    return moved.unionByName(kept).distinct()


def _mark(edges: DataFrame) -> tuple:
    """Count and order-free digest of an edge set; equal marks end the rounds."""
    digest = F.xxhash64("hi", "lo")
    return tuple(edges.agg(F.count("*"), F.bit_xor(digest), F.sum(F.pmod(digest, F.lit(1 << 31)))).first())


def label_min(edges: DataFrame, u: str = "a", v: str = "b", label: str = "cc-min") -> DataFrame:
    """As :func:`connected_components`, by handing the least known label to neighbours: a round per step of the diameter."""
    around = _ordered(edges.where(F.col(u).isNotNull() & F.col(v).isNotNull()), u, v)
    around = materialize(around.select(F.col("hi").alias("x"), F.col("lo").alias("y")).union(around.select("lo", "hi")), f"{label}-edges")
    current = materialize(around.groupBy(F.col("x").alias("vertex")).agg(F.least(F.min("x"), F.min("y")).alias("component")), f"{label}-0")
    i = 0
    while True:
        i += 1
        offered = around.join(current, around["y"] == current["vertex"]).groupBy("x").agg(F.min("component").alias("offer"))
        after = current.join(offered, current["vertex"] == offered["x"], "left").select("vertex", F.least("component", "offer").alias("component"), (F.col("offer") < F.col("component")).alias("moved"))
        after = materialize(after, f"{label}-{i}")
        done = not after.where("moved").head(1)
        last, current = current, after.select("vertex", "component")
        discard(last)
        if done:
            return current


#: Edges that the driver may hold (two identifiers each).
DRIVER_EDGES = 1_000_000


def driver_components(edges: DataFrame, u: str = "a", v: str = "b") -> DataFrame:
    """As :func:`connected_components`, by union-find on the driver; more than ``DRIVER_EDGES`` edges are refused."""
    few = materialize(_ordered(edges.where(F.col(u).isNotNull() & F.col(v).isNotNull()), u, v), "cc-driver")
    if few.count() > DRIVER_EDGES:
        raise ValueError(f"more than {DRIVER_EDGES} edges; use connected_components")
    up: dict = {}

    def find(x):
        up.setdefault(x, x)
        while up[x] != x:
            up[x] = up[up[x]]
            x = up[x]
        return x

    for hi, lo in few.collect():
        i, j = sorted((find(hi), find(lo)))
        up[j] = i
    kind = few.schema["hi"].dataType.simpleString()
    return edges.sparkSession.createDataFrame([(x, find(x)) for x in list(up)], f"vertex {kind}, component {kind}")


def connected_components(edges: DataFrame, u: str = "a", v: str = "b", label: str = "cc") -> DataFrame:
    """(vertex, component) for every vertex of an edge; component = least vertex.

    Null ends and self loops are left out.  An empty edge table gives an empty
    result.  Ties cannot occur: the least vertex is unique.
    """
    current = materialize(_ordered(edges.where(F.col(u).isNotNull() & F.col(v).isNotNull()), u, v), f"{label}-0")
    mark = _mark(current)
    for i in range(1, MAX_ROUNDS if mark[0] else 1):
        last, before = current, mark
        current = materialize(_small_star(_large_star(last)), f"{label}-{i}")
        discard(last)
        mark = _mark(current)
        if mark == before:
            break
    else:
        if not mark[0]:
            return current.select(F.col("hi").alias("vertex"), F.col("lo").alias("component"))
        raise RuntimeError(f"components did not converge in {MAX_ROUNDS} rounds")
    members = current.select(F.col("hi").alias("vertex"), F.col("lo").alias("component"))
    return members.unionByName(current.select(F.col("lo").alias("vertex"), F.col("lo").alias("component")).distinct())
