"""Line dedup by distinct-site spread: HyperLogLog sketches per line hash.

A line (``\\n``-split, with a word, trimmed of ASCII white space) is a candidate
when it stands on at least ``MIN_SITES`` distinct sites *and* in as many distinct
texts; the second spares the lines of a text that is merely copied to many sites.
A family of near copies can still make candidates of its own lines, because each
copy was edited and counts as a text.  Hence a candidate is boilerplate only if
it reaches both counts in documents that are mostly other text: those of which
candidates make up at most half of the characters.  Boilerplate lines go from
every document that has a line beside them; a document without one stays.

Each task builds a sketch of sites and one of texts for each line hash that it
meets; sketches of a line merge by aggregation.  An estimate far from the
threshold decides; lines near it get exact distinct counts, so the result is
that of exact counting.
"""

from __future__ import annotations

from pyspark.sql import Column, DataFrame, SparkSession
from pyspark.sql import functions as F
from pyspark.sql.types import MapType

from reuse_engine.llm.native_text import NON_SPACE
from reuse_engine.storage import dealt, discard, join_few, materialize

MIN_SITES = 8
#: Sketch precision: 2**12 registers, standard error 1.6 %.
LG_K = 12
#: Estimates within this share of the threshold are counted exactly: over six standard errors.
NEAR = 0.15
#: Line hashes that are put into the plan; more of them are joined.
INLINE_LINES = 20_000


def _trim(line: Column) -> Column:
    return F.regexp_replace(line, r"^[\x20\x09-\x0D]+|[\x20\x09-\x0D]+$", "")


def _key(line: Column) -> Column:
    """Hash of a trimmed line; null for a line without a word."""
    return F.when(line.rlike(NON_SPACE), F.xxhash64(_trim(line)))


def _hashed(c: str) -> Column:
    return F.xxhash64(F.coalesce(F.col(c), F.lit("")))


def _salt() -> Column:
    return F.xxhash64("site", "body")


def wide_lines(rows: DataFrame, min_sites: int = MIN_SITES) -> DataFrame:
    """(line) on ``min_sites`` distinct sites and in as many distinct texts; ``rows``: line, site, body, with repeats.

    Lines with fewer rows than that cannot qualify and get no sketch.  No step deals
    raw rows by their line: aggregates and sketches have a part in each task, and
    filters are a broadcast or a salted join.
    """
    ends = rows.groupBy("line").agg(
        F.count("*").alias("n"), F.min("site").alias("s0"), F.max("site").alias("s1"), F.min("body").alias("b0"), F.max("body").alias("b1")
    )
    often = materialize(ends.where((F.col("n") >= min_sites) & F.expr("s0 <> s1 and b0 <> b1")).select("line"), "lines-often")
    seen = join_few(rows, often, "line", _salt())
    sketches = seen.groupBy("line").agg(
        F.hll_sketch_estimate(F.hll_sketch_agg("site", LG_K)).alias("sites"), F.hll_sketch_estimate(F.hll_sketch_agg("body", LG_K)).alias("texts")
    )
    sketches = materialize(sketches.withColumn("least", F.least("sites", "texts")).where(F.col("least") >= min_sites * (1 - NEAR)), "lines-sketches")
    sure = F.col("least") > min_sites * (1 + NEAR)
    close = join_few(rows, sketches.where(~sure).select("line"), "line", _salt())
    sites = close.select("line", "site").distinct().groupBy("line").agg(F.count("*").alias("sites"))
    texts = close.select("line", "body").distinct().groupBy("line").agg(F.count("*").alias("texts"))
    exact = sites.join(texts, "line").where(F.least("sites", "texts") >= min_sites).select("line")
    found = materialize(sketches.where(sure).select("line").unionByName(exact), "lines-wide")
    discard(often, sketches)
    return found


def candidate_lines(docs: DataFrame, text_col: str = "text", site_col: str = "source", min_sites: int = MIN_SITES) -> DataFrame:
    """(line): hashes of the lines that all documents together make candidates."""
    body = docs.select(F.split(F.coalesce(F.col(text_col), F.lit("")), "\n").alias("ls"), _hashed(site_col).alias("site"), _hashed(text_col).alias("body"))
    rows = body.select(F.explode_outer(F.transform("ls", _key)).alias("line"), "site", "body").where("line is not null")
    rows = materialize(rows, "lines-rows")
    found = wide_lines(rows, min_sites)
    discard(rows)
    return found


def _with_hits(docs: DataFrame, text: Column, found: DataFrame, flag: str) -> DataFrame:
    """``docs`` with ``__ls``, the lines, and ``flag``, an array that says which of them are in ``found``."""
    ls = F.split(text, "\n")
    if found.count() <= INLINE_LINES:
        bad = [r[0] for r in found.collect()]
        hit = (lambda line: F.coalesce(_key(line).isin(bad), F.lit(False))) if bad else (lambda line: F.lit(False))
        return docs.withColumn("__ls", ls).withColumn(flag, F.transform("__ls", hit))
    split = docs.select(F.xxhash64(text).alias("__body"), ls.alias("ls"))
    line = split.select("__body", F.explode_outer(F.transform("ls", _key)).alias("line")).where("line is not null").distinct()
    drops = join_few(line, found, "line", F.xxhash64("__body")).groupBy("__body").agg(F.collect_set("line").alias("__drop"))
    drops = materialize(drops, "lines-drops")
    whole = F.xxhash64(*[F.col(c) for c in docs.columns if not isinstance(docs.schema[c].dataType, MapType)])
    out = join_few(docs.withColumn("__body", F.xxhash64(text)), drops, "__body", whole, "left", INLINE_LINES).drop("__body")
    out = out.withColumn("__ls", ls).withColumn(flag, F.transform("__ls", lambda x: F.coalesce(F.array_contains("__drop", _key(x)), F.lit(False))))
    return out.drop("__drop")


def _minor(flag: str) -> Column:
    """At most half of the characters stand on flagged lines."""
    gone = F.aggregate(F.zip_with("__ls", flag, lambda x, h: F.when(h, F.length(x)).otherwise(0)), F.lit(0), lambda a, b: a + b)
    whole = F.aggregate("__ls", F.lit(0), lambda a, x: a + F.length(x))
    return 2 * gone <= whole


def boilerplate_lines(docs: DataFrame, text_col: str = "text", site_col: str = "source", min_sites: int = MIN_SITES) -> DataFrame:
    """(line): hashes of candidates that reach both counts in documents that are mostly other text."""
    text = F.coalesce(F.col(text_col), F.lit(""))
    found = candidate_lines(docs, text_col, site_col, min_sites)
    if not found.head(1):
        return found
    hits = _with_hits(docs.select(text_col, site_col), text, found, "__hit").where(F.exists("__hit", lambda h: h) & _minor("__hit"))
    keys = F.array_distinct(F.transform(F.filter("__ls", lambda x, i: F.get("__hit", i)), _key))
    rows = materialize(hits.select(F.explode_outer(keys).alias("line"), _hashed(site_col).alias("site"), _hashed(text_col).alias("body")), "lines-hits")
    proven = wide_lines(rows, min_sites)
    discard(rows, found)
    return proven


def strip_boilerplate(docs: DataFrame, text_col: str = "text", site_col: str = "source", min_sites: int = MIN_SITES) -> DataFrame:
    """``docs`` with stripped texts and two more columns, n_lines and n_removed.

    Null text stays null with no lines.  A null site is one site.  Repeated rows
    are one text.  Columns named n_lines or n_removed are replaced.  An empty
    table gives an empty result.
    """
    docs = dealt(docs, "lines-docs")
    found = boilerplate_lines(docs, text_col, site_col, min_sites)
    text = F.coalesce(F.col(text_col), F.lit(""))
    out = _with_hits(docs, text, found, "__hit")
    own = F.exists(F.zip_with("__ls", "__hit", lambda x, h: x.rlike(NON_SPACE) & ~h), lambda o: o)
    kept = F.filter("__ls", lambda x, i: ~F.get("__hit", i))
    out = out.withColumn("__n", F.when(own, F.aggregate("__hit", F.lit(0), lambda a, h: a + h.cast("int"))).otherwise(0))
    return (
        out.withColumn(text_col, F.when(F.col("__n") > 0, F.array_join(kept, "\n")).otherwise(F.col(text_col)))
        .withColumn("n_lines", F.size(F.filter("__ls", lambda x: x.rlike(NON_SPACE))).cast("long"))
        .withColumn("n_removed", F.col("__n").cast("long"))
        .drop("__ls", "__hit", "__n")
    )


def op5_line_dedup(spark: SparkSession, sf_dir: str) -> DataFrame:
    docs = spark.read.parquet(f"{sf_dir}/documents.parquet").select("doc_id", "source", "text")
    return strip_boilerplate(docs).select("doc_id", "text", "n_lines", "n_removed")


_WIDE = f"GROUP BY line HAVING least(count(DISTINCT site), count(DISTINCT body)) >= {MIN_SITES}"

OP5_SQL = rf"""
WITH l AS (SELECT doc_id, coalesce(source, '') AS site, coalesce(text, '') AS body, text,
                  unnest(string_split(coalesce(text, ''), chr(10))) AS raw, generate_subscripts(string_split(coalesce(text, ''), chr(10)), 1) AS i FROM documents),
     k AS (SELECT *, CASE WHEN regexp_matches(raw, '[^\x20\x09-\x0D]') THEN regexp_replace(raw, '^[\x20\x09-\x0D]+|[\x20\x09-\x0D]+$', '', 'g') END AS line FROM l),
     candidate AS (SELECT line FROM k WHERE line IS NOT NULL {_WIDE}),
     c AS (SELECT k.*, line IS NOT NULL AND line IN (SELECT line FROM candidate) AS hit FROM k),
     mostly_other AS (SELECT doc_id FROM c GROUP BY doc_id HAVING 2 * coalesce(sum(length(raw)) FILTER (WHERE hit), 0) <= sum(length(raw))),
     bad AS (SELECT line FROM c SEMI JOIN mostly_other USING (doc_id) WHERE hit {_WIDE}),
     h AS (SELECT k.*, line IS NOT NULL AND line IN (SELECT line FROM bad) AS gone FROM k),
     d AS (SELECT doc_id, any_value(text) AS text, string_agg(raw, chr(10) ORDER BY i) FILTER (WHERE NOT gone) AS kept,
                  count(line) AS n_lines, count(*) FILTER (WHERE gone) AS n FROM h GROUP BY doc_id)
SELECT doc_id, CASE WHEN n > 0 AND n < n_lines THEN coalesce(kept, '') ELSE text END AS text, n_lines, CASE WHEN n < n_lines THEN n ELSE 0 END AS n_removed FROM d
"""
