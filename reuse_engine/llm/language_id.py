"""Language identification by prediction by partial matching (PPM).

Each language has a context tree of orders 0 to 3 over bytes.  A byte that its
context has seen costs ``-log2(count / (total + distinct))`` bits; else the escape
``distinct / (total + distinct)`` is paid and the next shorter context is asked,
down to a uniform code over all 256 bytes.  After learning, the counts are
frozen, so a text's exact code length is a sum of look-ups.  The language with the
shortest code wins.

The tree is sparse at any number of languages: a row of code lengths for every
four-byte and three-byte string that some language has seen (escapes included,
so that a hit needs no other look-up), a row of escapes for every context, and
two-byte strings in full.  Only A-Z are folded.

Learning takes at most about ``LEARN_DOCS`` whole texts per language, chosen by a
hash of the id among the allowed rows; the bound is a parameter.
"""

from __future__ import annotations

import re
from collections.abc import Iterator

import numpy as np
import pyarrow as pa
from pyspark.sql import Column, DataFrame, SparkSession
from pyspark.sql import functions as F

from reuse_engine.llm.worker_cache import limit_batches, only, released
from reuse_engine.storage import spread

LEARN_DOCS = 1_000
ORDER = 3
BYTES = 256
#: Bytes of text whose code lengths are looked up together.
CHUNK_BYTES = 1 << 18
#: Bytes over which a lead in code length counts in full towards the score.
EVIDENCE_BYTES = 64
UNKNOWN = "und"
PAD = b" " * ORDER
_LETTER = re.compile(r"[^\W\d_]")


def held_out(id_col: str) -> Column:
    """Rows that are never learned from: crc32 of the id as text, mod 3, is 1."""
    return F.coalesce(F.crc32(F.col(id_col).cast("string")) % 3 == 1, F.lit(False))


def _grams(body: bytes) -> np.ndarray:
    """A 32-bit number for each byte with its three predecessors; three spaces precede a text."""
    return _strings(np.frombuffer(PAD + body.lower(), np.uint8))


def _strings(raw: np.ndarray) -> np.ndarray:
    b = raw.astype(np.uint32)
    return (b[:-3] << 24) | (b[1:-2] << 16) | (b[2:-1] << 8) | b[3:]


@released
def _count(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
    held: dict[str, tuple[np.ndarray, np.ndarray]] = {}
    for batch in batches:
        for lang, body in zip(batch.column(0).to_pylist(), batch.column(1).to_pylist(), strict=True):
            found = np.unique(_grams(body or b""), return_counts=True)
            held[lang] = _merged([held[lang], found]) if lang in held else found
    for lang, (u, c) in held.items():
        yield pa.RecordBatch.from_arrays([pa.array([lang] * len(u)), pa.array(u.astype(np.int64)), pa.array(c.astype(np.int64))], names=["lang", "gram", "cnt"])


def _merged(parts: list) -> tuple[np.ndarray, np.ndarray]:
    u, at = np.unique(np.concatenate([p[0] for p in parts]), return_inverse=True)
    return u, np.bincount(at, np.concatenate([p[1] for p in parts]), len(u)).astype(np.int64)


class Rows:
    """Row numbers of sorted distinct 32-bit keys; a key that is not there has row ``len(keys)``.

    A hashed slot names one key; keys that lost their slot are searched.
    """

    def __init__(self, keys: np.ndarray) -> None:
        self.keys = keys.astype(np.uint32)
        self.shift = np.uint32(32 - max(4, int(4 * len(keys)).bit_length()))
        self.slot = np.zeros(1 << (32 - int(self.shift)), np.int32)
        at = self._hash(self.keys)
        self.slot[at] = np.arange(len(keys), dtype=np.int32)
        self.lost = np.flatnonzero(self.slot[at] != np.arange(len(keys))).astype(np.int32)

    def _hash(self, keys: np.ndarray) -> np.ndarray:
        return (keys * np.uint32(0x9E3779B1)) >> self.shift

    def find(self, keys: np.ndarray) -> np.ndarray:
        if not len(self.keys):
            return np.zeros(len(keys), np.int32)
        at = self.slot[self._hash(keys)]
        miss = np.flatnonzero(self.keys[at] != keys)
        if len(miss):
            asked, lost = keys[miss], self.keys[self.lost]
            found = np.full(len(miss), len(self.keys), np.int32)
            if len(lost):
                near = np.minimum(np.searchsorted(lost, asked), len(lost) - 1)
                found = np.where(lost[near] == asked, self.lost[near], found)
            at[miss] = found
        return at


class FrozenModel:
    """Code lengths, in bits, of all (context, byte) of all languages."""

    def __init__(self, langs: list[str], grams: list[np.ndarray], counts: list[np.ndarray]) -> None:
        self.langs = langs
        k = len(langs)
        seen = [self._orders(g.astype(np.int64), c) for g, c in zip(grams, counts, strict=True)]
        # order 0 and 1: every byte after every byte
        self.two = np.zeros((BYTES * BYTES, k), np.float32)
        self.escape2 = np.zeros((BYTES * BYTES, k), np.float32)
        union = [np.unique(np.concatenate([s[o][0] for s in seen] or [np.zeros(0, np.int64)])) for o in (2, 3)]
        contexts3 = np.unique(union[1] // BYTES)
        self.rows3, self.rows4, self.rows_c = Rows(union[0]), Rows(union[1]), Rows(contexts3)
        self.three = np.zeros((len(union[0]) + 1, k), np.float32)
        self.four = np.zeros((len(union[1]) + 1, k), np.float32)
        self.escape3 = np.zeros((len(contexts3) + 1, k), np.float32)
        for j, orders in enumerate(seen):
            one = self._next(orders[0], np.full(BYTES, 8.0), np.arange(BYTES), np.zeros(BYTES, np.int64), 1)[0]
            two, _ = self._next(orders[1], one[np.arange(BYTES * BYTES) % BYTES], np.arange(BYTES * BYTES), np.arange(BYTES * BYTES) // BYTES, BYTES)
            self.two[:, j] = two
            three, self.escape2[:, j] = self._next(orders[2], two[union[0] % BYTES**2], union[0], union[0] // BYTES, BYTES**2)
            self.three[:-1, j] = three
            shorter = self._shorter(union[1], j)
            four, escape = self._next(orders[3], shorter, union[1], np.searchsorted(contexts3, union[1] // BYTES), len(contexts3), contexts3)
            self.four[:-1, j], self.escape3[:-1, j] = four, escape

    @staticmethod
    def _orders(grams: np.ndarray, counts: np.ndarray) -> list[tuple[np.ndarray, np.ndarray]]:
        """(strings, counts) of one to four bytes."""
        out = []
        for o in range(ORDER + 1):
            u, at = np.unique(grams % BYTES ** (o + 1), return_inverse=True)
            out.append((u, np.bincount(at, counts, len(u))))
        return out

    @staticmethod
    def _next(seen: tuple, shorter: np.ndarray, strings: np.ndarray, place: np.ndarray, n: int, names: np.ndarray | None = None) -> tuple[np.ndarray, np.ndarray]:
        """Bits of ``strings`` at one order, and the escape of each of its ``n`` contexts (0: not seen).

        ``shorter``: their bits at the next shorter order; ``place``: number of their
        context among ``names``, or that context itself.
        """
        u, c = seen
        context = u // BYTES if names is None else np.searchsorted(names, u // BYTES)
        total, distinct = np.bincount(context, c, n), np.bincount(context, minlength=n)
        whole = total + distinct
        escape = np.where(whole > 0, -np.log2(np.maximum(distinct, 1) / np.maximum(whole, 1)), 0.0)
        bits = escape[place] + shorter
        at = np.searchsorted(strings, u)
        bits[at] = -np.log2(c / whole[context])
        return bits, escape

    def _shorter(self, strings: np.ndarray, j: int) -> np.ndarray:
        """Bits of four-byte strings at order 2."""
        s = (strings % BYTES**3).astype(np.uint32)
        row = self.rows3.find(s)
        unseen = self.escape2[s >> 8, j] + self.two[s & np.uint32(0xFFFF), j]
        return np.where(row < len(self.rows3.keys), self.three[row, j], unseen)

    def bits(self, strings: np.ndarray) -> np.ndarray:
        """Bits of each (context, byte) in every language."""
        row = self.rows4.find(strings)
        out = self.four[row]
        new = np.flatnonzero(row == len(self.rows4.keys))
        if len(new):
            s = strings[new]
            low = s & np.uint32(0xFFFFFF)
            row3 = self.rows3.find(low)
            cost = self.three[row3]
            rare = np.flatnonzero(row3 == len(self.rows3.keys))
            cost[rare] = self.escape2[low[rare] >> 8] + self.two[low[rare] & np.uint32(0xFFFF)]
            out[new] = cost + self.escape3[self.rows_c.find(s >> 8)]
        return out

    def code_lengths(self, body: bytes) -> np.ndarray:
        """Bits that each language takes for a text."""
        return self.all_lengths([body])[0]

    def all_lengths(self, bodies: list[bytes]) -> np.ndarray:
        """:meth:`code_lengths` of several texts, looked up together."""
        out = np.zeros((len(bodies), len(self.langs)))
        held: list[tuple[int, bytes]] = []
        size = 0

        def flush() -> None:
            nonlocal size
            if held:
                starts = np.cumsum([0] + [len(b) for _, b in held[:-1]])
                strings = np.concatenate([_strings(np.frombuffer(b, np.uint8)) for _, b in held])
                starts = starts - ORDER * np.arange(len(held))
                sums = np.add.reduceat(self.bits(strings), starts, axis=0, dtype=np.float64)
                np.add.at(out, [i for i, _ in held], sums)
                held.clear()
                size = 0

        for i, body in enumerate(bodies):
            whole = PAD + body.lower()
            for at in range(0, len(body), CHUNK_BYTES):
                held.append((i, whole[at : at + CHUNK_BYTES + ORDER]))
                size += len(held[-1][1])
                if size >= CHUNK_BYTES:
                    flush()
        flush()
        return out

    def predict(self, body: bytes | None) -> tuple[str, float]:
        return self.predict_all([body])[0]

    def predict_all(self, bodies: list[bytes | None]) -> list[tuple[str, float]]:
        """(language, score) of each text; ``und`` with score 0 for one without a letter."""
        able = [i for i, b in enumerate(bodies) if self.langs and b and _LETTER.search(b.decode("utf-8", "replace"))]
        out = [(UNKNOWN, 0.0)] * len(bodies)
        if able:
            bits = self.all_lengths([bodies[i] for i in able])
            best = bits.argmin(axis=1)
            lead = bits - bits[np.arange(len(able)), best][:, None]
            lead *= np.minimum(1.0, EVIDENCE_BYTES / np.array([len(bodies[i]) for i in able]))[:, None]
            scores = 1.0 / np.exp2(-np.minimum(lead, 500)).sum(axis=1)
            for i, k, p in zip(able, best.tolist(), scores.tolist(), strict=True):
                out[i] = (self.langs[k], p)
        return out


def _model(held) -> FrozenModel:
    """The tables are laid out once for each task."""
    m = held.value
    return only(("language", m["key"]), lambda: FrozenModel(m["langs"], m["grams"], m["counts"]))


def learn(docs: DataFrame, id_col: str = "doc_id", text_col: str = "text", lang_col: str = "lang", learn_docs: int = LEARN_DOCS) -> dict:
    """Counts per language, to be broadcast: a bounded sample's distinct four-byte grams."""
    allowed = docs.where(F.col(id_col).isNotNull() & F.col(lang_col).isNotNull() & F.col(text_col).isNotNull() & ~held_out(id_col))
    sizes = {r[0]: max(1, r[1] // learn_docs) for r in allowed.groupBy(lang_col).count().collect()}
    if not sizes:
        return {"key": "empty", "langs": [], "grams": [], "counts": []}
    every = F.element_at(F.create_map(*[F.lit(x) for kv in sizes.items() for x in kv]), F.col(lang_col))
    chosen = allowed.where(F.pmod(F.xxhash64(id_col), every) == 0).select(F.col(lang_col).alias("lang"), F.col(text_col).cast("binary").alias("body"))
    rows = chosen.mapInArrow(_count, "lang string, gram long, cnt long").groupBy("lang", "gram").agg(F.sum("cnt").alias("cnt")).toPandas()
    langs = sorted(rows["lang"].unique())
    parts = [rows[rows["lang"] == x].sort_values("gram") for x in langs]
    grams, counts = [p["gram"].to_numpy() for p in parts], [p["cnt"].to_numpy() for p in parts]
    return {"key": hash(tuple(int(c.sum()) for c in counts) + tuple(int(g.sum()) for g in grams)), "langs": langs, "grams": grams, "counts": counts}


def identify(docs: DataFrame, counts: dict, id_col: str = "doc_id", text_col: str = "text") -> DataFrame:
    """(``id_col``, held_out, lang_pred, score) for every row.

    ``und`` with score 0 where the text is null, empty or has no letter, or where
    nothing was learned.  Repeated rows are predicted each; equal code lengths go
    to the first language by name.
    """
    limit_batches(docs.sparkSession)
    held = docs.sparkSession.sparkContext.broadcast(counts)

    @released
    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        model = _model(held)
        for batch in batches:
            found = model.predict_all(batch.column(2).to_pylist())
            yield pa.RecordBatch.from_arrays(
                [batch.column(0), batch.column(1), pa.array([f[0] for f in found], pa.string()), pa.array([f[1] for f in found], pa.float64())],
                names=["id", "held_out", "lang_pred", "score"],
            )

    kind = docs.schema[id_col].dataType.simpleString()
    rows = spread(docs.select(id_col, text_col)).select(F.col(id_col).alias("id"), held_out(id_col).alias("held_out"), F.col(text_col).cast("binary").alias("body"))
    return rows.mapInArrow(run, f"id {kind}, held_out boolean, lang_pred string, score double").withColumnRenamed("id", id_col)


def keep_identified(docs: DataFrame, text_col: str = "text", least_score: float = 0.5) -> DataFrame:
    """Rows of ``docs`` whose language is known with at least that score.

    Null, empty and letterless texts go.  Rows are kept or dropped where they
    stand, with all their columns, whatever those are named, so nothing is
    shuffled; repeated rows and null ids are judged each.  An empty table, or one
    without a learned language, gives an empty result.
    """
    limit_batches(docs.sparkSession)
    held = docs.sparkSession.sparkContext.broadcast(learn(docs, text_col=text_col))
    at = docs.columns.index(text_col)

    @released
    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        model = _model(held)
        for batch in batches:
            found = model.predict_all(batch.column(at).cast(pa.binary()).to_pylist())
            yield batch.filter(pa.array([lang != UNKNOWN and score >= least_score for lang, score in found], pa.bool_()))

    return spread(docs).mapInArrow(run, docs.schema)


def op8_language_id(spark: SparkSession, sf_dir: str) -> DataFrame:
    docs = spark.read.parquet(f"{sf_dir}/documents.parquet").select("doc_id", "text", "lang")
    return identify(docs, learn(docs))
