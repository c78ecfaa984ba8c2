"""Similar pairs of units: pruning, candidate generation, bounded edit distance.

Candidates come from one of these plans; all but the last lose nothing that
their pruning keeps:

``theta``   all pairs of a corpus and origin over a grid of tasks (the exhaustive baseline);
``band``    an equi-join on logarithmic buckets of a length or an attribute, for the rules that bound one;
``qgram``   an equi-join on the rarest grams of a fingerprint (prefix filter),
            with equality of fingerprints where too few grams are required;
``chunk``   chunks of distinct fingerprints within bands of their lengths (:mod:`chunks`),
            the default of :func:`similar_pairs`; ``band`` there means this plan too,
            because similar pairs need no other member of a band;
``minhash`` bands of minimum hashes for long fingerprints and the exact plan for
            short ones, for corpora where exact plans cost too much; its loss is
            measured, not assumed.
"""

from __future__ import annotations

import hashlib

import numpy as np
import pandas as pd
from pyspark.sql import Column, DataFrame, Window
from pyspark.sql import functions as F

from reuse_engine.functions.symbols import bound, reaches, score_bp
from reuse_engine.operators.chunks import _Texts, common_symbols, compared, distances, member_pairs

THRESHOLD = 70
#: Rows and columns of the grid that deals all pairs of a corpus.
GRID = 8
#: Fingerprints of up to so many symbols are paired exactly beside the lossy plan.
SHORT = 12
#: Lengths that may pair lie in one bucket or in neighbours: a bucket spans the least
#: ratio that the rule allows, less one hundredth for rounding.
LENGTH_RATIO = 70
#: Units of one fingerprint that travel together, about.
MEMBERS = 4_096
SIDE = ["unit_id", "fp", "fp_len", "n_ops", "n_pieces", "n_distinct_ops", "n_terminators", "n_operand_bytes", "n_bytes"]
ATTRIBUTES = ["n_ops", "n_pieces", "n_distinct_ops", "n_terminators", "n_operand_bytes", "n_bytes"]


def _side(fps: DataFrame, s: str, extra: list[str] | None = None) -> DataFrame:
    keep = ["corpus", "origin", *(extra or [])]
    return fps.where("fp_len > 0").select(*keep, *[F.col(c).alias(f"{c}_{s}") for c in SIDE])


def prune_condition(prune: str | None, threshold: int = THRESHOLD) -> str:
    """SQL text of a pruning rule over two sides ``_a`` and ``_b``."""
    rules = {
        None: "true",
        "none": "true",
        "length": "10 * least(n_ops_a, n_ops_b) >= 7 * greatest(n_ops_a, n_ops_b)",
        "attrs": "10 * ("
        + " + ".join(f"cast(10 * least({c}_a, {c}_b) < 7 * greatest({c}_a, {c}_b) as int)" for c in ATTRIBUTES)
        + f") <= 3 * {len(ATTRIBUTES)}",
        "fp_len": f"100 * least(fp_len_a, fp_len_b) >= {threshold} * greatest(fp_len_a, fp_len_b)",
    }
    return rules["fp_len" if prune == "bag" else prune]


def bag_bound(a: Column, b: Column) -> Column:
    """Least edit distance that symbol counts allow: the larger excess of either side."""

    def excess(x: Column, y: Column) -> Column:
        gain = F.transform(F.array_distinct(F.split(x, "")), lambda s: F.greatest(_times(x, s) - _times(y, s), F.lit(0)))
        return F.aggregate(gain, F.lit(0), lambda t, v: t + v)

    return F.greatest(excess(a, b), excess(b, a))


def _times(text: Column, s: Column) -> Column:
    return F.length(text) - F.length(F.replace(text, s, F.lit("")))


def theta_candidates(fps: DataFrame, condition: str) -> DataFrame:
    """All pairs, dealt over a grid: units of cell row r meet those of cell column c in one of ``GRID ** 2`` tasks."""
    deal = F.pmod(F.xxhash64("unit_id"), F.lit(GRID)).cast("int")
    every = F.explode(F.sequence(F.lit(0), F.lit(GRID - 1)))
    dealt = fps.withColumn("own", deal).withColumn("other", every)
    a = _side(dealt.withColumnRenamed("own", "r").withColumnRenamed("other", "c"), "a", ["r", "c"])
    b = _side(dealt.withColumnRenamed("own", "c").withColumnRenamed("other", "r"), "b", ["r", "c"])
    return a.join(b, ["corpus", "origin", "r", "c"]).where(f"unit_id_a < unit_id_b and {condition}").drop("r", "c")


def attrs_candidates(fps: DataFrame, condition: str) -> DataFrame:
    """The attribute rule lets one attribute differ, so of any two one is within the ratio: two band joins hold every pair."""
    first, second = (band_candidates(fps, condition, by) for by in ("n_ops", "n_bytes"))
    near = F.expr("10 * least(n_ops_a, n_ops_b) >= 7 * greatest(n_ops_a, n_ops_b)")
    return first.where(near).unionByName(second.where(~near))


def length_bucket(n: Column, ratio: int = LENGTH_RATIO) -> Column:
    """Logarithmic bucket of a length: lengths that may pair lie in one or in neighbours."""
    return F.floor(F.log(F.greatest(n, F.lit(1)).cast("double")) / F.log(F.lit(100 / (ratio - 1)))).cast("int")


def band_candidates(fps: DataFrame, condition: str, by: str = "n_ops", ratio: int = LENGTH_RATIO) -> DataFrame:
    """Each pair meets once: the left side visits its bucket and both neighbours."""
    banded = fps.withColumn("bucket", length_bucket(F.col(by), ratio))
    a = _side(banded, "a", ["bucket"]).withColumn("bucket", F.explode(F.array(*[F.col("bucket") + k for k in (-1, 0, 1)])))
    b = _side(banded, "b", ["bucket"])
    return a.join(b, ["corpus", "origin", "bucket"]).where(f"unit_id_a < unit_id_b and {condition}").drop("bucket")


def gram_rows(fps: DataFrame, q: int = 2, extra: tuple[str, ...] = ()) -> DataFrame:
    """(corpus, origin, unit_id, fp_len, gram): the multiset of q-grams, occurrences numbered."""
    grams = F.transform(F.sequence(F.lit(1), F.col("fp_len") - q + 1), lambda i: F.substr(F.col("fp"), i, F.lit(q)))
    rows = fps.where(f"fp_len >= {q}").select("corpus", "origin", "unit_id", "fp_len", *extra, F.posexplode(grams).alias("i", "g"))
    nth = F.row_number().over(Window.partitionBy("corpus", "origin", "unit_id", "g").orderBy("i"))
    return rows.select("corpus", "origin", "unit_id", "fp_len", *extra, F.concat("g", F.lit("#"), nth.cast("string")).alias("gram"))


def qgram_candidates(fps: DataFrame, condition: str, threshold: int = THRESHOLD) -> DataFrame:
    """Pairs that share one of the rarest grams of both.

    With at most k = (100 - t) m div 100 edits, two fingerprints share m - 1 - 2k of
    their 2-grams.  ``least`` is the smallest such number over all lengths m that a
    partner can bring, so the first (grams - least + 1) grams in a global order,
    rarest first, have one in common.  Where ``least`` is not positive, fingerprints
    without an allowed edit are joined on equality and others by length.
    """
    partner = F.sequence(F.col("fp_len"), F.expr(f"cast((100 * fp_len) div {threshold} as int)"))
    edits = lambda m: F.floor((100 - threshold) * m / 100)
    sized = fps.where("fp_len > 0").withColumn("least", F.array_min(F.transform(partner, lambda m: m - 1 - 2 * edits(m))))
    sized = sized.withColumn("edits", F.array_max(F.transform(partner, edits)))
    grams = gram_rows(sized, extra=("least",))
    seen = grams.groupBy("corpus", "origin", "gram").agg(F.count("*").alias("df"))
    ranked = grams.join(seen, ["corpus", "origin", "gram"]).withColumn(
        "r", F.row_number().over(Window.partitionBy("corpus", "origin", "unit_id").orderBy("df", "gram"))
    )
    prefix = ranked.where("r <= fp_len - greatest(least, 1)").select("corpus", "origin", "unit_id", "fp_len", "gram")
    x = prefix.select("corpus", "origin", "gram", F.col("unit_id").alias("a"), F.col("fp_len").alias("la"))
    y = prefix.select("corpus", "origin", "gram", F.col("unit_id").alias("b"), F.col("fp_len").alias("lb"))
    near = f"a < b and 100 * least(la, lb) >= {threshold} * greatest(la, lb)"
    by_gram = x.join(y, ["corpus", "origin", "gram"]).where(near).select("corpus", "origin", "a", "b")
    short = sized.where("least <= 0 and edits = 0").select("corpus", "origin", "unit_id", "fp")
    equal = short.withColumnRenamed("unit_id", "a").join(short.withColumnRenamed("unit_id", "b"), ["corpus", "origin", "fp"]).where("a < b")
    loose = band_candidates(sized.where("least <= 0 and edits > 0"), prune_condition("fp_len", threshold), "fp_len", threshold)
    loose = loose.select("corpus", "origin", F.col("unit_id_a").alias("a"), F.col("unit_id_b").alias("b"))
    return _complete(fps, by_gram.unionByName(equal.select("corpus", "origin", "a", "b")).unionByName(loose).distinct(), condition)


def _complete(fps: DataFrame, ids: DataFrame, condition: str) -> DataFrame:
    """Both sides' columns for candidate ids (corpus, origin, a, b), with dist where the plan has measured it."""
    a, b = _side(fps, "a"), _side(fps, "b")
    keyed = ids.select("corpus", "origin", F.col("a").alias("unit_id_a"), F.col("b").alias("unit_id_b"), *[c for c in ids.columns if c == "dist"])
    return keyed.join(a, ["corpus", "origin", "unit_id_a"]).join(b, ["corpus", "origin", "unit_id_b"]).where(condition)


def chunk_candidates(fps: DataFrame, condition: str, threshold: int = THRESHOLD, keys: Column | None = None, whole: bool = True) -> DataFrame:
    """Pairs of units of equal fingerprints, and of fingerprints that reach the threshold (and share one of ``keys``), with dist.

    Pairs are made where distinct fingerprints meet and are not joined again; of both sides
    they have fp_len and, unless ``whole``, only the attributes of ``condition``.
    """
    rows = fps.where("fp_len > 0")
    held = [c for c in ATTRIBUTES if whole or f"{c}_a" in condition]
    at = ["corpus", "origin", "fp", "fp_len"]
    many = rows.groupBy(*at).agg(F.count("*").alias("n")).where(F.col("n") > MEMBERS).select(*at, F.ceil(F.col("n") / MEMBERS).alias("parts"))
    part = F.pmod(F.xxhash64("unit_id"), F.coalesce("parts", F.lit(1)))
    member = F.struct("unit_id", *[F.col(c).cast("bigint").alias(c) for c in held])
    dealt = rows.join(F.broadcast(many), at, "left").withColumn("part", part)
    kinds = dealt.groupBy(*at, "part").agg(F.min("unit_id").alias("unit_id"), F.collect_list(member).alias("m"))
    kinds = kinds.select(*at, "unit_id", F.col("m.unit_id").alias("ids"), *[F.col(f"m.{c}").alias(c) for c in held])
    kinds = kinds if keys is None else kinds.withColumn("keys", keys)
    return member_pairs(kinds, threshold, lambda n: length_bucket(n, threshold), held, keys is not None, whole).where(condition)


def minhash_candidates(fps: DataFrame, condition: str, threshold: int = THRESHOLD, bands: int = 32, rows: int = 2, q: int = 2, whole: bool = True) -> DataFrame:
    """Pairs that agree on all minimum hashes of one band, over numbered grams; lossy.

    A few edits change most grams of a short fingerprint, so pairs with one of up to
    ``SHORT`` symbols come from the exact plan over the lengths that these can meet.
    """
    starts = F.sequence(F.lit(1), F.greatest(F.col("fp_len") - q + 1, F.lit(1)))
    ordered = F.sort_array(F.transform(starts, lambda i: F.substr(F.col("fp"), i, F.lit(q))))
    nth = lambda s: F.transform(s, lambda g, i: F.concat(g, (i - F.array_position(s, g)).cast("string")))  # noqa: E731  # place among equal grams
    seeded = lambda ns, seed: F.array_min(F.transform(ns, lambda g: F.xxhash64(g, F.lit(seed))))
    least = lambda ns: [seeded(ns, seed) for seed in range(bands * rows)]
    hashed = lambda m: F.array(*[F.xxhash64(F.lit(i), *[F.get(m, F.lit(j)) for j in range(i * rows, (i + 1) * rows)]) for i in range(bands)])
    # grams, numbered grams and minimum hashes are each bound once, as the only element of an array
    bound_once = lambda c, f: F.get(F.transform(F.array(c), f), 0)
    keys = bound_once(ordered, lambda s: bound_once(nth(s), lambda ns: bound_once(F.array(*least(ns)), hashed)))
    met = chunk_candidates(fps.where(F.col("fp_len") > SHORT), condition, threshold, keys, whole)
    short = chunk_candidates(fps.where(F.col("fp_len") <= SHORT * 100 // threshold), condition, threshold, whole=whole)
    return met.unionByName(short.where(F.least("fp_len_a", "fp_len_b") <= SHORT))


def candidate_pairs(fps: DataFrame, how: str = "band", prune: str | None = "length", threshold: int = THRESHOLD, whole: bool = True) -> DataFrame:
    """Candidates of a plan under a pruning rule; ``band`` needs a rule that bounds lengths or attributes.

    Without ``whole``, plans that measure pairs give no more of both sides than the rule needs.
    """
    condition = prune_condition(prune, threshold)
    if how == "band" and prune in (None, "none"):
        raise ValueError("without a pruning rule no bucket holds both sides of a pair; use theta or qgram")
    made = {
        "theta": lambda: theta_candidates(fps, condition),
        "band": lambda: attrs_candidates(fps, condition) if prune == "attrs" else band_candidates(fps, condition) if prune == "length" else band_candidates(fps, condition, "fp_len", threshold),
        "qgram": lambda: qgram_candidates(fps, condition, threshold),
        "chunk": lambda: chunk_candidates(fps, condition, threshold, whole=whole or prune == "bag"),
        "minhash": lambda: minhash_candidates(fps, condition, threshold, whole=whole or prune == "bag"),
    }[how]()
    if prune == "bag":
        far = bag_bound(F.col("fp_a"), F.col("fp_b"))
        made = made.where(100 * (F.greatest("fp_len_a", "fp_len_b") - far) >= threshold * F.greatest("fp_len_a", "fp_len_b"))
    return made


_PAIR = ["corpus", "origin", "a", "b", "la", "lb", "dist", "max_len", "score_bp"]


def scored(candidates: DataFrame) -> DataFrame:
    """All candidates with distance and score."""
    named = candidates.withColumn("max_len", F.greatest("fp_len_a", "fp_len_b")).withColumn("dist", F.levenshtein("fp_a", "fp_b"))
    named = named.withColumn("score_bp", score_bp(F.col("dist").cast("bigint"), F.col("max_len").cast("bigint")))
    return named.select("corpus", "origin", F.col("unit_id_a").alias("a"), F.col("unit_id_b").alias("b"), F.col("fp_len_a").alias("la"), F.col("fp_len_b").alias("lb"), "dist", "max_len", "score_bp")


def similar_pairs(
    fps: DataFrame, threshold: int = THRESHOLD, inclusive: bool = True, how: str = "chunk", prune: str | None = "length"
) -> DataFrame:
    """Pairs that reach the threshold; the distance stops at the bound that it implies, where the plan has not measured it."""
    c = candidate_pairs(fps, "chunk" if how == "band" else how, prune, threshold, False).withColumn("max_len", F.greatest("fp_len_a", "fp_len_b"))
    within = c.where(f"dist <= {bound(threshold, 'max_len', inclusive)}") if "dist" in c.columns else c.withColumn("dist", F.expr(f"levenshtein(fp_a, fp_b, greatest({bound(threshold, 'max_len', inclusive)}, 0))")).where("dist >= 0")
    out = within.withColumn("score_bp", score_bp(F.col("dist").cast("bigint"), F.col("max_len").cast("bigint")))
    out = out.where(reaches(F.col("score_bp"), threshold, inclusive) if not inclusive else F.expr(f"100 * (max_len - dist) >= {threshold} * max_len"))
    return out.select("corpus", "origin", F.col("unit_id_a").alias("a"), F.col("unit_id_b").alias("b"), F.col("fp_len_a").alias("la"), F.col("fp_len_b").alias("lb"), "dist", "max_len", "score_bp").select(*_PAIR)


def compared_counts(fps: DataFrame, by: str = "n_ops") -> DataFrame:
    """Units, possible and compared pairs per corpus and origin, from length counts alone.

    A running total over the distinct lengths says how many units are at most 10/7
    as long as a given one, so neither pairs of units nor pairs of lengths are formed.
    """
    lengths = fps.where("fp_len > 0").groupBy("corpus", "origin", by).agg(F.count("*").alias("c"))
    up = Window.partitionBy("corpus", "origin").orderBy(by).rowsBetween(Window.unboundedPreceding, 0)
    total = lengths.withColumn("upto", F.sum("c").over(up))
    marks = total.select("corpus", "origin", F.col(by).cast("bigint").alias("at"), F.lit(0).alias("kind"), F.col("c"), F.col("upto"), F.col("upto").alias("mark"))
    asks = total.select("corpus", "origin", F.expr(f"(10 * {by}) div 7").cast("bigint").alias("at"), F.lit(1).alias("kind"), "c", "upto", F.lit(None).cast("bigint").alias("mark"))
    last = Window.partitionBy("corpus", "origin").orderBy("at", "kind").rowsBetween(Window.unboundedPreceding, 0)
    known = marks.unionByName(asks).withColumn("near", F.last("mark", ignorenulls=True).over(last)).where("kind = 1")
    return known.groupBy("corpus", "origin").agg(F.sum("c").alias("n_units"), F.sum(F.expr("c * (c - 1) div 2 + c * (near - upto)")).alias("n_compared")).select(
        "corpus", "origin", "n_units", F.expr("n_units * (n_units - 1) div 2").alias("n_possible"), "n_compared"
    )


def _pair_hashes(a: np.ndarray, b: np.ndarray) -> np.ndarray:
    """First 64 bits of md5(a|b), which order as the hexadecimal strings do."""
    digests = b"".join([hashlib.md5(f"{x}|{y}".encode()).digest() for x, y in zip(a, b)])
    return np.frombuffer(digests, ">u8")[::2].astype(np.uint64)


def sample_pairs(fps: DataFrame, per_bin: int) -> DataFrame:
    """(corpus, origin, a, b, score_bp): compared pairs under the length rule, without those that cannot be among the first of a bin.

    All pairs are scored and hashed in the cells where they meet; a cell keeps, of each
    ten-wide score bin, the ``per_bin`` pairs of least hash and what ties with the last of them.
    """

    def choose(y: pd.DataFrame, x: pd.DataFrame, pairs) -> pd.DataFrame:
        ys, xs = _Texts(list(y["fp"])), _Texts(list(x["fp"]))
        ids_y, ids_x = y["unit_id"].to_numpy(object), x["unit_id"].to_numpy(object)
        kept = (np.zeros(0, np.int64), np.zeros(0, np.int64), np.zeros(0, np.int64), np.zeros(0, np.uint64))
        for i, j in pairs:
            longer = np.maximum(ys.size[i], xs.size[j])
            a, b = ids_y[i], ids_x[j]
            swap = b < a
            found = (i, j, 10000 * (longer - distances(ys, xs, i, j)) // longer, _pair_hashes(np.where(swap, b, a), np.where(swap, a, b)))
            i, j, score, order = (np.concatenate(both) for both in zip(kept, found))
            least = []
            for k in range(10):
                at = np.flatnonzero(np.minimum(score // 1000, 9) == k)
                least.append(at if len(at) <= per_bin else at[order[at] <= np.partition(order[at], per_bin - 1)[per_bin - 1]])
            some = np.concatenate(least)
            kept = (i[some], j[some], score[some], order[some])
        a, b = ids_y[kept[0]], ids_x[kept[1]]
        swap = (b < a).astype(bool)
        return pd.DataFrame({"a": np.where(swap, b, a), "b": np.where(swap, a, b), "score_bp": kept[2]})

    made = compared(fps.where("fp_len > 0"), ["fp"], "n_ops", LENGTH_RATIO, length_bucket, choose, "a string, b string, score_bp long")
    return made.select("corpus", "origin", "a", "b", "score_bp")


def left_counts(fps: DataFrame, rule: str) -> DataFrame:
    """(corpus, n_compared): pairs that a pruning rule leaves at :data:`THRESHOLD`, none of which is a row.

    Pairs within one length are counted from running totals, those of more attributes or of
    symbol counts in the cells where they meet.
    """
    rows = fps.where("fp_len > 0")
    if rule in ("none", "length", "fp_len"):
        made = compared_counts(fps, "fp_len" if rule == "fp_len" else "n_ops").select("corpus", F.col("n_possible" if rule == "none" else "n_compared").alias("n"))
    elif rule == "bag":

        def alike(y: pd.DataFrame, x: pd.DataFrame, pairs) -> pd.DataFrame:
            common, m = common_symbols(list(y["fp"]), list(x["fp"])), y["fp_len"].to_numpy(np.int64)
            return pd.DataFrame({"n": [sum(int((100 * common(i, j) >= THRESHOLD * m[i]).sum()) for i, j in pairs)]})

        made = compared(rows, ["fp"], "fp_len", THRESHOLD, length_bucket, alike, "n long")
    else:

        def near(by: str) -> DataFrame:
            def count(y: pd.DataFrame, x: pd.DataFrame, pairs) -> pd.DataFrame:
                of_y, of_x = ({c: side[c].to_numpy(np.int64) for c in ATTRIBUTES} for side in (y, x))
                n = 0
                for i, j in pairs:
                    apart = {c: 10 * np.minimum(of_y[c][i], of_x[c][j]) < 7 * np.maximum(of_y[c][i], of_x[c][j]) for c in ATTRIBUTES}
                    left = 10 * sum(v.astype(np.int8) for v in apart.values()) <= 3 * len(ATTRIBUTES)
                    n += int((left if by == "n_ops" else left & apart["n_ops"]).sum())
                return pd.DataFrame({"n": [n]})

            return compared(rows, ATTRIBUTES, by, LENGTH_RATIO, length_bucket, count, "n long")

        made = near("n_ops").unionByName(near("n_bytes"))  # one attribute may differ, see :func:`attrs_candidates`
    return made.groupBy("corpus").agg(F.sum("n").alias("n_compared")).where("n_compared > 0")


def similar_by_rule(fps: DataFrame, rules: tuple[str, ...]) -> DataFrame:
    """(corpus, n_all and a count for each rule) of all similar pairs, and of those that each rule leaves."""
    every = chunk_candidates(fps, "true").where(f"dist <= {bound(THRESHOLD, 'greatest(fp_len_a, fp_len_b)', True)}")
    far = bag_bound(F.col("fp_a"), F.col("fp_b"))
    most = F.greatest("fp_len_a", "fp_len_b")
    left = lambda r: F.expr(prune_condition(r)) & (100 * (most - far) >= THRESHOLD * most if r == "bag" else F.lit(True))
    return every.groupBy("corpus").agg(F.count("*").alias("n_all"), *[F.count_if(left(r)).alias(r) for r in rules])
