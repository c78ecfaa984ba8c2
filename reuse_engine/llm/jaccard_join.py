"""N-gram Jaccard join on a trie of globally ordered shingle sets.

Two texts are linked when their sets of distinct five-word shingles have a
Jaccard similarity of at least 3/4, tested on integers (``7 * both >= 3 *
(n_a + n_b)``), so no link is lost or added by rounding.

1. One pass over the texts names each set by a 128-bit digest; equal sets are
   one vertex from here on, whatever the number of copies.
2. The global order puts shingles that repeat inside partitions last, by their
   summed counts, and all others by hash.  The heaviest are listed; the rest
   share a table of buckets, so that both parts have a bound at any size.  A set's
   prefix is its first ``n - ceil(3n/4) + 1`` shingles: linked sets share one of them.
3. Shingles in the prefixes of two or more sets give candidate edges.  Pairs
   that met by chance go by a bitmap bound (no more shingles can be shared than
   have their bit set on the other side), which is exact too.  The components of
   the remaining edges are *families*; no link leaves a family.
4. A family is one block; a large one is dealt into chunks of about ``CHUNK`` sets or
   ``CHUNK_SHINGLES`` shingles, by size bands such that linked sets stand in the
   same band or in neighbours.  A block is stored as a path-compressed trie, and a
   probe descends it with the overlap of the shared path, cutting subtrees that
   cannot reach the required overlap with what is left on either side.
5. Probing runs until only one large component and a rest are left; the rest is
   probed against every chunk of its band and the next ones, which is exact: of two
   sets in different components at least one belongs to a rest.
6. Links become components by contraction of the edge table.

Nothing is capped: the constants only choose between exact ways.  No step deals
raw rows by a key that a large group shares: what is known to be frequent is
listed, and joins with such lists are by broadcast or on a salted key.
"""

from __future__ import annotations

from collections.abc import Iterator

import numpy as np
import pandas as pd
import pyarrow as pa
from pyspark.sql import DataFrame, SparkSession, Window
from pyspark.sql import functions as F

from reuse_engine.graph import connected_components
from reuse_engine.llm.shingles import Shingler, set_digest
from reuse_engine.llm.worker_cache import limit_batches, released
from reuse_engine.storage import dealt, discard, few_broadcast, join_few, materialize

#: Most shingles that the broadcast part of the global order lists (12 bytes each), and buckets of the others.
ORDER_LIMIT, BUCKETS = 1_000_000, 1 << 18
#: Shingles found in up to so many prefixes give all their pairs, others a star.
SMALL = 128
#: Sets, and shingles of all sets, in one block.
CHUNK, CHUNK_SHINGLES = 256, 4_000_000
#: Sets of a band that every chunk near it is probed with first.
HUBS = 8
#: Sizes of one band are within this ratio, a little more than 4/3.
BAND = 1.34
#: Vertices that may be broadcast (8 bytes each) to pick the texts of families.
BROADCAST_IDS = 2_000_000
#: Shingles that a task counts at one time.
COUNTED = 4_000_000

_FEATURES = "id long, n long, sig binary, token long, cnt long"
_ENTRIES = "token long, id64 long, n int, pos int, late boolean"


#: Rows of a batch that are Python objects at one time.
SLICE_ROWS = 1_000


def _bytes(batch: pa.RecordBatch, name: str) -> list:
    return batch.column(batch.schema.get_field_index(name)).to_pylist()


def _slices(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
    for batch in batches:
        for at in range(0, len(batch), SLICE_ROWS):
            yield batch.slice(at, SLICE_ROWS)


def _repeated(tokens: list[np.ndarray]) -> Iterator[pa.RecordBatch]:
    """A row per shingle that two of the sets have; empties the list."""
    every = np.concatenate(tokens)
    tokens.clear()
    every.sort()
    u, c = np.unique(every[1:][every[1:] == every[:-1]], return_counts=True)  # all but the first of each
    u, c = u.view(np.int64), (c + 1).astype(np.int64)
    for i in range(0, len(u), 50_000):
        k = len(u[i : i + 50_000])
        nothing = pa.nulls(k, pa.int64())
        yield pa.RecordBatch.from_arrays([nothing, nothing, pa.nulls(k, pa.binary()), pa.array(u[i : i + k]), pa.array(c[i : i + k])], names=["id", "n", "sig", "token", "cnt"])


@released
def _features(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
    """A row per text, and rows of shingles that several sets have."""
    shingler, seen, tokens, held = Shingler(), set(), [], 0
    for batch in _slices(batches):
        ids, ns, sigs = _bytes(batch, "id"), [], []
        for s in shingler.each(_bytes(batch, "body")):
            sig = set_digest(s)
            ns.append(len(s))
            sigs.append(sig)
            if len(s) and sig not in seen:
                seen.add(sig)
                tokens.append(s)
                held += len(s)
        nothing = pa.nulls(len(ids), pa.int64())
        yield pa.RecordBatch.from_arrays(
            [pa.array(ids, pa.int64()), pa.array(ns, pa.int64()), pa.array(sigs, pa.binary()), nothing, nothing],
            names=["id", "n", "sig", "token", "cnt"],
        )
        if held >= COUNTED:
            yield from _repeated(tokens)
            held = 0
    if tokens:
        yield from _repeated(tokens)


class Order:
    """The global order: unlisted shingles by their bucket's weight and then by hash, then listed ones by weight."""

    def __init__(self, listed: np.ndarray, weight: np.ndarray, buckets: np.ndarray) -> None:
        self.listed, self.weight, self.buckets = listed, weight, buckets

    def sort(self, s: np.ndarray) -> tuple[np.ndarray, int]:
        """Sorted hashes ``s`` in order, and the number of those that are not listed."""
        if not len(s):
            return s, 0
        is_late = np.zeros(len(s), bool)
        if len(self.listed):
            at = np.minimum(np.searchsorted(self.listed, s), len(self.listed) - 1)
            is_late = self.listed[at] == s
        rest = s[~is_late]
        if len(self.buckets):
            w = self.buckets[(rest % np.uint64(len(self.buckets))).astype(np.int64)]
            some = w > 0
            if some.any():
                heavy = rest[some]
                rest = np.concatenate([rest[~some], heavy[np.argsort(w[some], kind="stable")]])
        if len(rest) == len(s):
            return rest, len(s)
        last = s[is_late]
        return np.concatenate([rest, last[np.argsort(self.weight[at[is_late]], kind="stable")]]), len(rest)


def prefix_length(n: int) -> int:
    return n - -(-3 * n // 4) + 1


def _prefixes(order):
    @released
    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        ranked, shingler, seen = order.value, Shingler(), set()
        for batch in _slices(batches):
            parts, ids, ns, pos, late = [], [], [], [], []
            for s in shingler.each(_bytes(batch, "body")):
                if not len(s) or (sig := set_digest(s)) in seen:
                    continue
                seen.add(sig)
                k = prefix_length(len(s))
                ordered, unlisted = ranked.sort(s)
                at = np.arange(k, dtype=np.int32)
                parts.append(ordered[:k])
                ids.append(np.full(k, int.from_bytes(sig[:8], "little", signed=True), np.int64))
                ns.append(np.full(k, len(s), np.int32))
                pos.append(at)
                late.append(at >= unlisted)
            if parts:
                yield pa.RecordBatch.from_arrays(
                    [pa.array(np.concatenate(parts).view(np.int64)), pa.array(np.concatenate(ids)), pa.array(np.concatenate(ns)), pa.array(np.concatenate(pos)), pa.array(np.concatenate(late))],
                    names=["token", "id64", "n", "pos", "late"],
                )

    return run


def bitmap(s: np.ndarray) -> bytes:
    """A power of two of bits, at least two for each shingle; shingle h sets bit h mod size."""
    bits = 1 << max(6, min(17, int(2 * len(s) - 1).bit_length()))
    flags = np.zeros(bits, np.uint8)
    flags[(s & np.uint64(bits - 1)).astype(np.int64)] = 1
    return np.packbits(flags, bitorder="little").tobytes()


def _folded(bits: int, size: int, to: int) -> int:
    while size > to:
        size //= 2
        bits = (bits >> size) | (bits & ((1 << size) - 1))
    return bits


def may_link(a: bytes, na: int, b: bytes, nb: int) -> bool:
    """False only for sets that cannot be linked."""
    size = 8 * min(len(a), len(b))
    x = _folded(int.from_bytes(a, "little"), 8 * len(a), size)
    y = _folded(int.from_bytes(b, "little"), 8 * len(b), size)
    return 7 * min(na - (x & ~y).bit_count(), nb - (y & ~x).bit_count()) >= 3 * (na + nb)


def _made(column: str, make):
    """(id, column): ``make`` of the shingles of each text."""

    @released
    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        shingler = Shingler()
        for batch in _slices(batches):
            made = pa.array([make(s) for s in shingler.each(_bytes(batch, "body"))], pa.binary())
            yield pa.RecordBatch.from_arrays([batch.column(batch.schema.get_field_index("id")), made], names=["id", column])

    return run


def _plausible(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
    for batch in batches:
        rows = zip(*[_bytes(batch, c) for c in ("bits_a", "na", "bits_b", "nb")], strict=True)
        keep = pa.array([may_link(*r) for r in rows], pa.bool_())
        yield batch.select(["a", "b"]).filter(keep)


class Trie:
    """Path-compressed trie over sets, most frequent shingle first.

    An edge is (tokens, depth at its end, child edges, least and largest set size
    below, first and last place of the sets below, sets that end here).
    """

    def __init__(self, sets: list[np.ndarray]) -> None:
        u, inverse, counts = np.unique(np.concatenate(sets), return_inverse=True, return_counts=True)
        rank = np.empty(len(u), np.int64)
        rank[np.lexsort((u, -counts))] = np.arange(len(u))
        self.vocabulary, self.rank = u, rank
        ends = np.cumsum([len(s) for s in sets])
        self.ranked = [np.sort(rank[inverse[e - len(s) : e]]) for s, e in zip(sets, ends, strict=True)]
        self.n = np.array([len(s) for s in sets])
        self.order = np.array(sorted(range(len(sets)), key=lambda i: self.ranked[i].astype(">i8").tobytes()))
        self.root = self._build()
        self.bits = 1 << max(6, min(16, int(2 * np.median(self.n) - 1).bit_length()))
        self.maps = np.stack([self._map(s) for s in sets])

    def _map(self, s: np.ndarray) -> np.ndarray:
        flags = np.zeros(self.bits, np.uint8)
        flags[(s & np.uint64(self.bits - 1)).astype(np.int64)] = 1
        return np.packbits(flags).view(np.uint64)

    def _build(self) -> list:
        top: list = []
        work = [(0, len(self.order), 0, top)]  # places of sets that share their first ``depth`` shingles
        while work:
            i, stop, depth, out = work.pop()
            while i < stop:
                head = self.ranked[self.order[i]]
                lo, hi = i + 1, stop  # the run of sets that share head[depth]
                while lo < hi:
                    mid = (lo + hi) // 2
                    if self.ranked[self.order[mid]][depth] == head[depth]:
                        lo = mid + 1
                    else:
                        hi = mid
                last = self.ranked[self.order[lo - 1]]
                k = min(len(head), len(last))
                differ = np.nonzero(head[depth:k] != last[depth:k])[0]  # of a sorted run, first and last differ first
                end = depth + int(differ[0]) if len(differ) else k
                here = i
                while here < lo and len(self.ranked[self.order[here]]) == end:
                    here += 1
                below = self.n[self.order[i:lo]]
                kids: list = []
                out.append((head[depth:end], end, kids, int(below.min()), int(below.max()), i, lo, here))
                if here < lo:
                    work.append((here, lo, end, kids))
                i = lo
        return top

    def probe(self, s: np.ndarray, wanted: np.ndarray | None = None) -> list[int]:
        """Indexes of the (wanted) sets linked with ``s``.

        Sets that the bitmap bound excludes are not wanted, and a subtree without
        a wanted set is not entered.
        """
        nx, x = len(s), self._map(s)
        mine_only = np.bitwise_count(x & ~self.maps).sum(axis=1, dtype=np.int64)
        theirs_only = np.bitwise_count(self.maps & ~x).sum(axis=1, dtype=np.int64)
        may = 7 * np.minimum(nx - mine_only, self.n - theirs_only) >= 3 * (nx + self.n)
        if wanted is not None:
            may &= wanted
        if not may.any():
            return []
        upto = np.concatenate([[0], np.cumsum(may[self.order])]).tolist()
        at = np.minimum(np.searchsorted(self.vocabulary, s), len(self.vocabulary) - 1)
        mine = self.rank[at[self.vocabulary[at] == s]]
        has = np.zeros(len(self.vocabulary) + 1, np.int32)
        has[mine] = 1
        until = np.concatenate([[0], np.cumsum(has)])  # of mine, those of lower rank
        total = len(mine)
        found, stack = [], [(self.root, 0)]
        while stack:
            edges, overlap = stack.pop()
            for tokens, depth, kids, least, largest, first, stop, here in edges:
                if upto[first] == upto[stop]:
                    continue
                both = overlap + int(has[tokens].sum())
                left = total - int(until[int(tokens[-1]) + 1])
                if 7 * (both + min(largest - depth, left)) < 3 * (nx + least):
                    continue
                if here > first and 7 * both >= 3 * (nx + depth):
                    found += [j for j in self.order[first:here].tolist() if may[j]]
                if kids:
                    stack.append((kids, both))
        return found


class Forest:
    """Components of 0..n-1 as labels; the least index names each."""

    def __init__(self, n: int) -> None:
        self.label = np.arange(n)

    def find(self, i: int) -> int:
        return int(self.label[i])

    def join(self, i: int, j: int) -> None:
        i, j = sorted((self.find(i), self.find(j)))
        if i != j:
            self.label[self.label == j] = i

    def rest(self) -> list[int]:
        """All that are not in the largest component."""
        if not len(self.label):
            return []
        names, counts = np.unique(self.label, return_counts=True)
        return np.nonzero(self.label != names[counts.argmax()])[0].tolist()


def block_links(sets: list[np.ndarray], probes: list[int] | None = None) -> Forest:
    """Components of a block; ``probes`` limits who is probed (all are stored).

    A probe asks only for sets of other components than its own.
    """
    trie, forest = Trie(sets), Forest(len(sets))

    def ask(i: int) -> None:
        for j in trie.probe(sets[i], forest.label != forest.label[i]):
            forest.join(i, j)

    if probes is None:
        first = min(HUBS, len(sets))
        for i in range(first):
            ask(i)
        probes = [i for i in forest.rest() if i >= first]
    for i in probes:
        ask(i)
    return forest


def _block(pdf: pd.DataFrame) -> pd.DataFrame:
    """Star edges of the components of one chunk; rows with ``probe`` are probed.

    A chunk whose rows are all of role ``own`` or ``hub`` is joined with itself.
    """
    pdf = pdf.sort_values(["probe", "id"], ascending=[False, True]).drop_duplicates("id")
    sets = [np.frombuffer(b, dtype=np.uint64) for b in pdf["shingles"]]
    ids = pdf["id"].to_numpy()
    n_probes = int(pdf["probe"].sum())
    forest = block_links(sets, list(range(n_probes)) if n_probes else None)
    roots = [forest.find(i) for i in range(len(ids))]
    keep = [i for i, r in enumerate(roots) if r != i]
    return pd.DataFrame({"a": ids[[roots[i] for i in keep]], "b": ids[keep]}, columns=["a", "b"]).astype("int64")


def _candidate_edges(entries: DataFrame) -> tuple[DataFrame, DataFrame]:
    """(star edges, pairs) between sets that share a prefix shingle.

    ``entries``: (token, id, n, pos), distinct.  A frequent shingle gives a star
    around its least set; a rare one its pairs that pass the size and position
    bounds, which hold at the first shingle that a linked pair shares.
    """
    counts = entries.groupBy("token").agg(F.count("*").alias("m"), F.min("id").alias("a"))
    many = materialize(counts.where(F.col("m") > SMALL).select("token", "a"), "jaccard-many")
    star = join_few(entries, many, "token", F.xxhash64("id")).where("a <> id").select("a", F.col("id").alias("b")).distinct()
    few = join_few(entries, many.select("token"), "token", F.xxhash64("id"), "left_anti")
    x = few.select("token", F.col("id").alias("a"), F.col("n").alias("na"), F.col("pos").alias("pa"))
    y = few.select("token", F.col("id").alias("b"), F.col("n").alias("nb"), F.col("pos").alias("pb"))
    pairs = x.join(y, "token").where(
        "a < b and 4 * least(na, nb) >= 3 * greatest(na, nb) and 7 * least(na - pa, nb - pb) >= 3 * (na + nb)"
    )
    return star, pairs.select("a", "na", "b", "nb").distinct()


def jaccard_components(docs: DataFrame, id_col: str = "doc_id", text_col: str = "text") -> DataFrame:
    """Return (``id_col``, n_shingles, component_id) for every row of ``docs``.

    Null or wordless text: n_shingles 0, its own component.  Fewer than five
    words: one shingle.  Rows that repeat an id give a row each; null ids keep a
    null component.  Other columns are ignored, whatever their names.  An empty
    table gives an empty result.
    """
    spark = docs.sparkSession
    limit_batches(spark)
    body = dealt(docs.select(F.col(id_col).cast("long").alias("id"), F.col(text_col).cast("binary").alias("body")), "jaccard-texts")
    features = materialize(body.mapInArrow(_features, _FEATURES), "jaccard-features")
    texts = features.where("n is not null").select("id", "n", "sig")

    order = spark.sparkContext.broadcast(_order(features.where("token is not null").select("token", "cnt")))
    entries = body.mapInArrow(_prefixes(order), _ENTRIES)
    # a listed shingle is known to be shared: its rows meet nobody and are dealt evenly
    over = Window.partitionBy("token", "alone")
    shared = (
        entries.withColumn("alone", F.when(F.col("late"), F.col("id64")))
        .withColumn("lo", F.min("id64").over(over))
        .withColumn("hi", F.max("id64").over(over))
        .where("late or lo <> hi")
        .select("token", "id64", "n", "pos")
        .distinct()
    )
    shared = materialize(shared, "jaccard-shared")

    reps = texts.where("n > 0").groupBy("sig").agg(F.min("id").alias("rep"), F.first("n").alias("n"), F.count("*").alias("copies"))
    reps = materialize(reps.where("rep is not null"), "jaccard-sets")
    named = reps.withColumn("id64", _low_long("sig")).select("id64", "rep", F.col("n").cast("int").alias("n"))
    on = materialize(shared.join(named, ["id64", "n"]).select("token", F.col("rep").alias("id"), "n", "pos"), "jaccard-entries")
    star, pairs = _candidate_edges(on)
    star, pairs = materialize(star, "jaccard-star"), materialize(pairs, "jaccard-pairs")
    discard(shared, on)
    ids = pairs.select(F.col("a").alias("id")).union(pairs.select("b")).distinct()
    bits = _of_texts(body, ids, "bits", bitmap)
    weighed = pairs.join(bits.toDF("a", "bits_a"), "a").join(bits.toDF("b", "bits_b"), "b")
    plausible = weighed.mapInArrow(_plausible, "a long, b long")
    families = connected_components(star.unionByName(plausible), label="jaccard-family")
    families = materialize(families.select(F.col("vertex").alias("id"), F.col("component").alias("family")), "jaccard-families")
    discard(star, pairs)
    sets = _of_texts(body, families.select("id"), "shingles", np.ndarray.tobytes)
    links = _links(families, sets)
    roots = connected_components(links, label="jaccard-links")

    by_set = reps.join(roots.select(F.col("vertex").alias("rep"), "component"), "rep", "left").where("copies > 1 or component is not null")
    by_set = materialize(by_set.select("sig", F.coalesce("component", "rep").alias("component")), "jaccard-result")
    return join_few(texts, by_set, "sig", F.xxhash64("id"), "left").select(
        F.col("id").alias(id_col), F.col("n").alias("n_shingles"), F.when(F.col("id").isNotNull(), F.coalesce("component", "id")).alias("component_id")
    )


def _of_texts(body: DataFrame, ids: DataFrame, column: str, make) -> DataFrame:
    """(id, column) for the texts of some ids: only these are shingled again, and no text is shuffled if the ids can be broadcast."""
    wanted = body.join(few_broadcast(materialize(ids, f"jaccard-{column}-ids"), BROADCAST_IDS), "id", "left_semi")
    made = wanted.mapInArrow(_made(column, make), f"id long, {column} binary")
    return materialize(made, f"jaccard-{column}").dropDuplicates(["id"])


def _low_long(sig: str):
    """First eight bytes of a digest as a little-endian signed long."""
    digits = F.hex(F.substring(F.col(sig), 1, 8))
    swapped = F.concat(*[F.substring(digits, 15 - 2 * i, 2) for i in range(8)])
    high = F.conv(F.substring(swapped, 1, 8), 16, 10).cast("long")
    low = F.conv(F.substring(swapped, 9, 8), 16, 10).cast("long")
    return F.shiftleft(high, 32).bitwiseOR(low)


def _order(counts: DataFrame) -> Order:
    """The global order from partial counts.

    Counts are summed over all partitions.  The least weight that is still listed
    rises with the total, so that the list has at most ``ORDER_LIMIT`` shingles; the
    others give the largest weight of each of ``BUCKETS`` buckets.
    """
    total = counts.agg(F.sum("cnt")).first()[0] or 0
    least = max(4, -(-total // ORDER_LIMIT))
    listed = F.col("cnt") >= least
    bucket = F.pmod(F.col("token"), F.lit(BUCKETS))  # a power of two: the same for signed and unsigned hashes
    summed = counts.groupBy("token").agg(F.sum("cnt").alias("cnt"))
    rows = summed.groupBy(listed.alias("listed"), F.when(listed, F.col("token")).otherwise(bucket).alias("key")).agg(F.max("cnt").alias("cnt")).toPandas()
    late, other = rows[rows["listed"]], rows[~rows["listed"].astype(bool)]
    token = late["key"].to_numpy(np.int64).view(np.uint64)
    at = np.argsort(token)
    buckets = np.zeros(BUCKETS if len(other) else 0, np.uint32)
    buckets[other["key"].to_numpy(np.int64)] = np.minimum(other["cnt"].to_numpy(np.int64), (1 << 32) - 1)
    return Order(token[at], late["cnt"].to_numpy(np.int64)[at].astype(np.uint32 if total < 1 << 32 else np.uint64), buckets)


def _links(families: DataFrame, sets: DataFrame) -> DataFrame:
    """Links (a, b) whose components are those of all links within families."""
    stored = families.join(sets, "id").withColumn("n", (F.octet_length("shingles") / 8).cast("long"))
    stored = stored.withColumn("band", F.floor(F.log("n") / float(np.log(BAND))).cast("int"))
    stored = materialize(stored, "jaccard-stored")
    salt = F.xxhash64("id")
    whole = stored.groupBy("family").agg(F.count("*").alias("m"), F.sum("n").alias("tokens"))
    large = materialize(whole.where((F.col("m") > CHUNK) | (F.col("tokens") > CHUNK_SHINGLES)).select("family"), "jaccard-large")
    small = join_few(stored, large, "family", salt, "left_anti").select("id", "family", F.lit(0).alias("band"), F.lit(0).cast("long").alias("chunk"), "shingles", F.lit(0).alias("probe"))
    if not large.head(1):
        near = materialize(_run_blocks(small), "jaccard-near")
        discard(stored, large)
        return near

    rows = join_few(stored, large, "family", salt)
    counted = rows.groupBy("family", "band").agg(F.count("*").alias("m"), F.sum("n").alias("tokens"))
    chunks = F.greatest(F.ceil(F.col("m") / CHUNK), F.ceil(F.col("tokens") / CHUNK_SHINGLES))
    bands = materialize(counted.select(F.struct("family", "band").alias("at"), chunks.alias("chunks")), "jaccard-bands")
    placed = join_few(rows.withColumn("at", F.struct("family", "band")), bands, "at", salt)
    placed = placed.withColumn("chunk", F.pmod(F.xxhash64("id"), F.col("chunks"))).select("id", "family", "band", "chunk", "shingles")
    placed = materialize(placed, "jaccard-placed")
    # hubs: of each chunk first, so that no band is sorted in one task
    key = F.struct(F.xxhash64("id").alias("h"), F.col("id"))
    of_chunk = F.row_number().over(Window.partitionBy("family", "band", "chunk").orderBy(key))
    firsts = placed.select("family", "band", "chunk", "id", of_chunk.alias("r")).where(F.col("r") <= HUBS)
    of_band = F.row_number().over(Window.partitionBy("family", "band").orderBy(key))
    hub_ids = materialize(firsts.withColumn("q", of_band).where(F.col("q") <= HUBS).select("id"), "jaccard-hubs")
    hubs = placed.join(few_broadcast(hub_ids, BROADCAST_IDS), "id", "left_semi")
    own = placed.withColumn("probe", F.lit(0))
    first = small.unionByName(own).unionByName(_near_chunks(hubs, bands).withColumn("probe", F.lit(0)))
    near = materialize(_run_blocks(first), "jaccard-near")

    # who is outside the largest component of its family is probed in every chunk near its band
    roots = connected_components(near, label="jaccard-chunks")
    rooted = placed.select("id", "family").join(roots.withColumnRenamed("vertex", "id"), "id", "left")
    rooted = materialize(rooted.withColumn("component", F.coalesce("component", "id")), "jaccard-rooted")
    main = (
        rooted.groupBy("family", "component").agg(F.count("*").alias("k"))
        .groupBy("family").agg(F.max_by("component", F.struct("k", "component")).alias("main"))
    )
    rest = join_few(rooted, materialize(main, "jaccard-main"), "family", salt).where("component <> main").select("id")
    rest = placed.join(few_broadcast(materialize(rest, "jaccard-rest-ids"), BROADCAST_IDS), "id", "left_semi")
    probes = _near_chunks(rest, bands).withColumn("probe", F.lit(1))
    asked = probes.select("family", "band", "chunk").distinct().withColumn("at", F.struct("family", "band", "chunk")).select("at")
    asked = materialize(asked, "jaccard-asked")  # chunks that nobody asks are not built again
    again = join_few(own.withColumn("at", F.struct("family", "band", "chunk")), asked, "at", salt, "left_semi").drop("at")
    second = materialize(_run_blocks(again.unionByName(probes)), "jaccard-rest")
    discard(stored, placed, rooted)
    return near.unionByName(second)


def _near_chunks(rows: DataFrame, bands: DataFrame) -> DataFrame:
    """Each set once for every chunk of its band and of the two beside it."""
    there = F.explode(F.array(*[F.struct("family", (F.col("band") + k).cast("int").alias("band")) for k in (-1, 0, 1)]))
    moved = rows.drop("chunk").withColumn("at", there).drop("band")
    met = join_few(moved, bands, "at", F.xxhash64("id"))
    return met.select("id", "family", F.col("at.band").alias("band"), F.explode(F.sequence(F.lit(0).cast("long"), F.col("chunks") - 1)).alias("chunk"), "shingles")


def _run_blocks(rows: DataFrame) -> DataFrame:
    return rows.select("id", "family", "band", "chunk", "shingles", "probe").groupBy("family", "band", "chunk").applyInPandas(_block, "a long, b long")


def keep_one_per_group(docs: DataFrame, id_col: str = "doc_id", text_col: str = "text") -> DataFrame:
    """Rows of ``docs`` whose id is the least of its component.

    Texts without words and rows without an id stay.  Rows that repeat an id stand
    or fall together: all go if one of them has a lesser id in its group.  All
    columns are kept, whatever their names; an empty table gives an empty result.
    """
    groups = jaccard_components(docs, id_col, text_col)
    drop = materialize(groups.where(F.col(id_col) != F.col("component_id")).select(id_col).distinct(), "jaccard-drop")
    return docs.join(few_broadcast(drop, BROADCAST_IDS), id_col, "left_anti").select(docs.columns)


def op2_ngram_jaccard_join(spark: SparkSession, sf_dir: str) -> DataFrame:
    return jaccard_components(spark.read.parquet(f"{sf_dir}/documents.parquet"))


#: Every pair of documents that share a shingle is counted, so this is for small tables.
OP2_SQL = r"""
WITH RECURSIVE w AS (SELECT doc_id, regexp_extract_all(translate(coalesce(text, ''), 'ABCDEFGHIJKLMNOPQRSTUVWXYZ', 'abcdefghijklmnopqrstuvwxyz'), '[^\x20\x09-\x0D]+') AS w FROM documents),
     s AS MATERIALIZED (SELECT DISTINCT doc_id, CASE WHEN len(w) >= 5 THEN unnest([array_to_string(w[i:i + 4], ' ') FOR i IN range(1, greatest(len(w) - 3, 2))])
                                                     ELSE '#' || array_to_string(w, ' ') END AS g FROM w WHERE len(w) > 0),
     n AS MATERIALIZED (SELECT doc_id, count(*) AS n FROM s GROUP BY 1),
     e AS MATERIALIZED (SELECT a, b FROM (SELECT x.doc_id AS a, y.doc_id AS b, count(*) AS k FROM s x JOIN s y ON x.g = y.g AND x.doc_id <> y.doc_id GROUP BY 1, 2) p
       JOIN n ON n.doc_id = p.a JOIN n m ON m.doc_id = p.b WHERE 100 * k >= 75 * (n.n + m.n - k)),
     r(v, l) AS (SELECT a, a FROM e UNION SELECT e.b, r.l FROM r JOIN e ON e.a = r.v AND e.b >= r.l)
SELECT doc_id, coalesce(n.n, 0) AS n_shingles, coalesce(c.l, doc_id) AS component_id
FROM documents LEFT JOIN n USING (doc_id) LEFT JOIN (SELECT v AS doc_id, min(l) AS l FROM r GROUP BY 1) c USING (doc_id)
"""
