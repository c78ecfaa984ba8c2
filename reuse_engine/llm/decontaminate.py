"""Benchmark decontamination: size-partitioned MinHash containment search.

A benchmark item is far shorter than the documents that may hold it, so the
similarity that counts is containment: the share of the item's distinct
five-word shingles that the whole document holds.  Items are partitioned by
their number of shingles, and each partition has a sketch size and a candidate
rule of its own (``PARTITIONS``): a bottom-k MinHash sketch is the k shingles of an
item with the least hash values, and the share of them found in a document
estimates the containment without bias, whatever the document's length.  The
smallest items are their own sketch, so their estimate is exact.  In the other
partitions a document is a candidate from the number of hits on that an item of
containment 3/4 misses with a probability below ``MISS``; larger items can afford a
larger sketch, whose rule lets fewer chance candidates through.  Candidates are
verified by exact containment (``4 * shared >= 3 * size``).

Words are lower-cased runs of letters, marks and digits of any script (all else
separates, typographic quotes and dashes too), so a passage that changed its
punctuation is still found.  Items of one to four words are one shingle of their
own length, found wherever the words stand in a row.
"""

from __future__ import annotations

from math import comb

from pyspark.sql import Column, DataFrame, SparkSession, Window
from pyspark.sql import functions as F

from reuse_engine.llm.native_text import WIDTH, words
from reuse_engine.storage import dealt, few_broadcast, materialize

SEPARATORS = r"[^\p{L}\p{M}\p{N}]+"
#: (most shingles, sketch size) of each partition but the last, which has the size LAST_SKETCH; the first is its own sketch.
PARTITIONS, LAST_SKETCH = ((32, 32), (128, 32), (512, 48)), 64
MISS = 1e-7


def least_hits(k: int, miss: float = MISS) -> int:
    """Most hits that can be asked of a sketch of ``k`` so that containment 3/4 falls short with a probability below ``miss``."""
    below, need = 0.0, 0
    while (below := below + comb(k, need) * 0.75**need * 0.25 ** (k - need)) < miss:
        need += 1
    return need


def _windows(w: str, k: int) -> Column:
    """A hash for each window of ``k`` words."""
    n = F.size(w)
    at = F.transform(F.sequence(F.lit(0), n - k), lambda i: F.xxhash64(*[F.get(F.col(w), i + j) for j in range(k)]))
    return F.when(n >= k, at).otherwise(F.array().cast("array<bigint>"))


def _shingled(df: DataFrame, id_col: str, text_col: str, out: str, widths: list[int]) -> DataFrame:
    """(out, h): hashes of the windows of each width; unnested by ``explode_outer`` only.

    A plain ``explode`` infers a filter on the array's size, which the optimizer
    pushes to the scan with the whole expression inlined, once per array access.
    """
    w = df.select(F.col(id_col).alias(out), words(F.lower(F.col(text_col)), SEPARATORS).alias("w"))
    return w.select(out, F.concat(*[_windows("w", k) for k in widths]).alias("h"))


def item_shingles(benchmark: DataFrame, item_col: str, item_text: str) -> DataFrame:
    """(item, width, token) for each distinct shingle of each item."""
    w = benchmark.where(F.col(item_col).isNotNull()).select(F.col(item_col).alias("item"), words(F.lower(F.col(item_text)), SEPARATORS).alias("w"))
    width = F.least(F.size("w"), F.lit(WIDTH))
    own = F.get(F.array(*[_windows("w", k) for k in range(1, WIDTH + 1)]), width - 1)
    return w.select("item", width.alias("width"), F.explode_outer(F.array_distinct(own)).alias("token")).where("token is not null").distinct()


def sketches(tokens: DataFrame) -> DataFrame:
    """(item, size, partition, token, in_sketch, need) for each distinct shingle of each item."""
    by_item = Window.partitionBy("item")
    ranked = tokens.withColumn("size", F.count("*").over(by_item)).withColumn(
        "r", F.row_number().over(by_item.orderBy(F.xxhash64("token"), "token"))
    )
    size, partition, sketch, need = F.col("size"), F.lit(len(PARTITIONS)), F.lit(LAST_SKETCH), F.lit(least_hits(LAST_SKETCH))
    for i, (most, k) in reversed(list(enumerate(PARTITIONS))):
        here = size <= most
        partition, sketch = F.when(here, i).otherwise(partition), F.when(here, k).otherwise(sketch)
        need = F.when(here, F.ceil(3 * size / 4) if i == 0 else F.lit(least_hits(k))).otherwise(need)
    return ranked.select(
        "item", "width", size.cast("long").alias("size"), partition.alias("partition"), "token", (F.col("r") <= sketch).alias("in_sketch"), need.cast("long").alias("need")
    )


def contained_items(
    docs: DataFrame, benchmark: DataFrame, id_col: str = "doc_id", text_col: str = "text", item_col: str = "item_id", item_text: str = "text"
) -> DataFrame:
    """(doc_id, item_id, n_item, n_shared) of items with containment of 3/4 or more.

    Null or wordless texts and items match nothing.  Repeated rows of an id count
    as one text each; their shingles are pooled under the id.  Equal items are
    reported each.  Null ids are left out.  Empty tables give an empty result.
    """
    items = materialize(sketches(item_shingles(benchmark, item_col, item_text)), "decontaminate-items")
    widths = sorted({WIDTH} | {r[0] for r in items.select("width").distinct().collect()})
    search = few_broadcast(items.where("in_sketch").select("item", "partition", "token", "need"))
    body = dealt(docs.where(F.col(id_col).isNotNull()).select(F.col(id_col).alias("id"), F.col(text_col).alias("body")), "decontaminate-texts")
    hashed = _shingled(body, "id", "body", "id", widths)
    hits = hashed.select("id", F.explode_outer("h").alias("token")).join(search, "token").distinct()
    found = hits.groupBy("id", "item", "partition").agg(F.count("*").alias("hits"), F.first("need").alias("need"))
    candidates = materialize(found.where("hits >= need").select("id", "item"), "decontaminate-candidates")

    wanted = few_broadcast(candidates.select("id").distinct())
    again = _shingled(body.join(wanted, "id", "left_semi"), "id", "body", "id", widths)
    pairs = again.select("id", F.explode_outer(F.array_distinct("h")).alias("token"))
    full = few_broadcast(items.select("item", "size", "token"))
    shared = pairs.join(full, "token").distinct().join(candidates, ["id", "item"], "left_semi")
    counted = shared.groupBy("id", "item").agg(F.first("size").alias("n_item"), F.count("*").alias("n_shared"))
    return counted.where("4 * n_shared >= 3 * n_item").select(
        F.col("id").alias(id_col), F.col("item").alias(item_col), "n_item", "n_shared"
    )


def drop_contaminated(docs: DataFrame, benchmark: DataFrame, id_col: str = "doc_id", text_col: str = "text") -> DataFrame:
    """Rows of ``docs`` that hold no benchmark item.

    Null and empty texts and rows without an id stay.  Rows that repeat an id stand
    or fall together, as their shingles are pooled.  All columns are kept, whatever
    their names; an empty table gives an empty result.
    """
    held = materialize(contained_items(docs, benchmark, id_col, text_col).select(id_col).distinct(), "decontaminate-held")
    return docs.join(few_broadcast(held), id_col, "left_anti").select(docs.columns)


def op1_benchmark_decontamination(spark: SparkSession, sf_dir: str) -> DataFrame:
    docs, items = (spark.read.parquet(f"{sf_dir}/{t}.parquet") for t in ("documents", "benchmark"))
    return contained_items(docs, items)


_WORDS = r"""SELECT id, list_filter(regexp_split_to_array(lower(text), '[^\p{{L}}\p{{M}}\p{{N}}]+'), lambda x: x <> '') AS w FROM {src}"""
_GRAMS = "SELECT DISTINCT id, unnest([array_to_string(w[i:i + {k} - 1], ' ') FOR i IN range(1, len(w) - {k} + 2)]) AS token FROM {src} WHERE len(w) >= {k}"

OP1_SQL = f"""
WITH bw AS ({_WORDS.format(src="(SELECT item_id AS id, text FROM benchmark WHERE item_id IS NOT NULL)")}),
     dw AS ({_WORDS.format(src="(SELECT doc_id AS id, text FROM documents WHERE doc_id IS NOT NULL)")}),
     b AS ({_GRAMS.format(k=5, src="bw")} UNION SELECT id, array_to_string(w, ' ') FROM bw WHERE len(w) BETWEEN 1 AND 4),
     d AS (SELECT id, token FROM ({" UNION ".join(_GRAMS.format(k=k, src="dw") for k in range(1, 6))}) SEMI JOIN b USING (token)),
     n AS (SELECT id, count(*) AS n_item FROM b GROUP BY id)
SELECT d.id AS doc_id, b.id AS item_id, n.n_item, count(*) AS n_shared
FROM d JOIN b ON d.token = b.token JOIN n ON n.id = b.id
GROUP BY ALL HAVING 4 * count(*) >= 3 * n.n_item
"""
