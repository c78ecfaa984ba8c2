"""SentencePiece encoding and decoding on the tokenizers library.

The model protobuf is parsed here; normaliser, metaspace marker, piece scores or
merges and byte fallback are rebuilt as a ``tokenizers`` pipeline, for unigram
and for BPE models.  Where no piece has a marker after another character and the
normaliser is the identity, a text's segments (marker run and word) are encoded
independently, so every distinct segment is encoded once for each task, in
multithreaded batches, and looked up after that; a BPE model takes several short
segments in one call.  Any other model encodes whole texts in batches.  Parity with the SentencePiece library is verified for every
distinct segment (or text), and every text is decoded and compared.
"""

from __future__ import annotations

import hashlib
import itertools
import os
import re
import struct
from collections.abc import Iterator
from dataclasses import dataclass, field

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from reuse_engine.llm.worker_cache import limit_batches, only, released, trim
from reuse_engine.storage import spread

MODEL_FILE = "/opt/tokenizers/piece_bpe_32k.model"
MARK = "▁"
NORMAL, UNKNOWN, CONTROL, USER, UNUSED, BYTE = 1, 2, 3, 4, 5, 6
UNIGRAM, BPE = 1, 2
#: Segments that a task remembers, characters of a batch of whole texts, and segments encoded at one time.
REMEMBERED_SEGMENTS, BATCH_CHARS = 200_000, 2_000_000
LEARN_SEGMENTS = 8_000
#: Segments of one call of a library, and characters of a segment that goes with others.
JOINED, JOINED_CHARS = 16, 64
SLICE_ROWS = 200
THREADS = 2


def _fields(data: bytes) -> Iterator[tuple[int, int | bytes]]:
    """(field number, value) of a protobuf message, in order."""
    at = 0

    def varint() -> int:
        nonlocal at
        value = shift = 0
        while True:
            b = data[at]
            at += 1
            value |= (b & 127) << shift
            shift += 7
            if b < 128:
                return value

    while at < len(data):
        key = varint()
        kind = key & 7
        if kind == 0:
            yield key >> 3, varint()
            continue
        size = {1: 8, 5: 4}.get(kind) or varint()
        yield key >> 3, data[at : at + size]
        at += size


@dataclass
class PieceModel:
    """What a SentencePiece model file says; field numbers are those of its public schema."""

    pieces: list[str] = field(default_factory=list)
    scores: list[float] = field(default_factory=list)
    kinds: list[int] = field(default_factory=list)
    model_type: int = UNIGRAM
    byte_fallback: bool = False
    charsmap: bytes = b""
    add_dummy_prefix: bool = True
    remove_extra_whitespaces: bool = True
    escape_whitespaces: bool = True

    @classmethod
    def parse(cls, data: bytes) -> PieceModel:
        out = cls()
        for number, value in _fields(data):
            if number == 1:
                row = dict(_fields(value))
                out.pieces.append(row.get(1, b"").decode())
                out.scores.append(struct.unpack("<f", row[2])[0] if 2 in row else 0.0)
                out.kinds.append(row.get(3, NORMAL))
            elif number == 2:
                row = dict(_fields(value))
                out.model_type, out.byte_fallback = row.get(3, UNIGRAM), bool(row.get(35, 0))
            elif number == 3:
                row = dict(_fields(value))
                out.charsmap = row.get(2, b"")
                out.add_dummy_prefix = bool(row.get(3, 1))
                out.remove_extra_whitespaces = bool(row.get(4, 1))
                out.escape_whitespaces = bool(row.get(5, 1))
        return out

    @property
    def unknown(self) -> int:
        return self.kinds.index(UNKNOWN)

    @property
    def by_segment(self) -> bool:
        """True if segments can be encoded one by one."""
        plain = not self.charsmap and self.add_dummy_prefix and not self.remove_extra_whitespaces and self.escape_whitespaces
        return plain and not any(k == NORMAL and MARK in p.lstrip(MARK) for p, k in zip(self.pieces, self.kinds, strict=True)) and USER not in self.kinds

    def merges(self) -> list[tuple[str, str]]:
        """All ways to join two pieces to a third, best score first."""
        ids = {p: i for i, p in enumerate(self.pieces)}
        usable = {p for p, k in zip(self.pieces, self.kinds, strict=True) if k in (NORMAL, USER)}
        out = []
        for p in usable:
            for k in range(1, len(p)):
                if p[:k] in usable and p[k:] in usable:
                    out.append((-self.scores[ids[p]], ids[p], ids[p[:k]], ids[p[k:]], (p[:k], p[k:])))
        return [m[-1] for m in sorted(out)]

    def core(self):
        """The ``tokenizers`` model without normaliser."""
        from tokenizers import Tokenizer, models

        if self.model_type == UNIGRAM:
            return Tokenizer(models.Unigram(list(zip(self.pieces, self.scores, strict=True)), unk_id=self.unknown, byte_fallback=self.byte_fallback))
        vocab = {p: i for i, p in enumerate(self.pieces)}
        return Tokenizer(models.BPE(vocab=vocab, merges=self.merges(), unk_token=self.pieces[self.unknown], fuse_unk=True, byte_fallback=self.byte_fallback, cache_capacity=0))

    def tokenizer(self):
        """The whole pipeline for whole texts."""
        from tokenizers import Regex, decoders, normalizers

        out = self.core()
        steps = [normalizers.Precompiled(self.charsmap)] if self.charsmap else []
        if self.remove_extra_whitespaces:
            steps += [normalizers.Replace(Regex("^ +| +$"), ""), normalizers.Replace(Regex(" {2,}"), " ")]
        if self.add_dummy_prefix:
            steps.append(normalizers.Prepend(MARK))
        if self.escape_whitespaces:
            steps.append(normalizers.Replace(" ", MARK))
        out.normalizer = normalizers.Sequence(steps)
        ends = [decoders.Replace(MARK, " "), decoders.ByteFallback(), decoders.Fuse()]
        out.decoder = decoders.Sequence([*ends, decoders.Strip(" ", 1, 0)] if self.add_dummy_prefix else ends)
        return out


class PieceCodec:
    """Encodes and decodes texts; ``bad`` holds segments where the libraries differ."""

    def __init__(self, data: bytes, threads: int = THREADS) -> None:
        import sentencepiece

        os.environ["TOKENIZERS_PARALLELISM"] = "true" if threads > 1 else "false"
        os.environ.setdefault("RAYON_NUM_THREADS", str(threads))
        self.model = PieceModel.parse(data)
        self.threads = threads
        self.other = sentencepiece.SentencePieceProcessor(model_proto=data)
        self.known: dict[str, bytes] = {}
        self.bad: set[str] = set()
        self.fast = self.model.by_segment
        self.backend = self.model.core() if self.fast else self.model.tokenizer()
        #: Joined segments can be told apart where every one opens with a piece that starts with the marker.
        self.joins = self.fast and self.model.model_type == BPE and MARK in self.model.pieces
        self.opens = np.array([p.startswith(MARK) for p in self.model.pieces])
        self.surface = pa.array([self._surface(p, k) for p, k in zip(self.model.pieces, self.model.kinds, strict=True)], pa.large_binary())

    @staticmethod
    def _surface(piece: str, kind: int) -> bytes:
        if kind == BYTE:
            return bytes([int(piece[3:5], 16)])
        if kind == CONTROL:
            return b""
        return " ⁇ ".encode() if kind == UNKNOWN else piece.replace(MARK, " ").encode()

    @staticmethod
    def segments(text: str) -> list[str]:
        """Segments without their first marker; joined by a marker each they are the text."""
        if "  " not in text and MARK not in text and text[:1] != " " and text[-1:] != " ":
            return text.split(" ") if text else []
        whole = MARK + text.replace(" ", MARK) if text else ""
        return [s[1:] for s in re.findall(f"{MARK}+[^{MARK}]*", whole)]

    def _learn(self, new: list[str]) -> None:
        """Encode segments that were not met yet, in multithreaded batches."""
        alone = new
        if self.joins:
            fits = [s for s in new if 0 < len(s) <= JOINED_CHARS and MARK not in s]
            if self._learn_joined(fits):
                alone = [s for s in new if s not in self.known]
        if alone:
            self._learn_alone(alone)

    def _learn_joined(self, new: list[str]) -> bool:
        """Encode segments without inner markers, several to a call; False if the libraries differ on one of them."""
        calls = [new[i : i + JOINED] for i in range(0, len(new), JOINED)]
        made = self.backend.encode_batch_fast([MARK + MARK.join(c) for c in calls], add_special_tokens=False)
        mine = np.fromiter(itertools.chain.from_iterable(m.ids for m in made), np.int32)
        others = self.other.encode([" ".join(c) for c in calls], num_threads=self.threads)
        if not np.array_equal(mine, np.fromiter(itertools.chain.from_iterable(others), np.int32)):
            return False
        at = np.flatnonzero(self.opens[mine])
        if len(at) != len(new):
            return False
        flat, ends = mine.tobytes(), [*(at * 4).tolist(), len(mine) * 4]
        self.known.update(zip(new, (flat[i:j] for i, j in itertools.pairwise(ends)), strict=True))
        return True

    def _learn_alone(self, new: list[str]) -> None:
        mine = [m.ids for m in self.backend.encode_batch_fast([MARK + s for s in new], add_special_tokens=False)]
        plain = [s if MARK not in s else s.replace(MARK, " ") for s in new]
        others = self.other.encode(plain, num_threads=self.threads)
        if "" in new:  # the library gives an empty text no marker
            others[new.index("")] = [self.other.piece_to_id(MARK)]
        if mine != others:
            self.bad.update(s for s, m, o in zip(new, mine, others, strict=True) if m != o)
        flat = np.fromiter(itertools.chain.from_iterable(mine), np.int32).tobytes()
        ends = np.cumsum([0, *map(len, mine)]) * 4
        self.known.update(zip(new, (flat[i:j] for i, j in itertools.pairwise(ends.tolist())), strict=True))

    def encode(self, texts: list[str]) -> list[tuple[np.ndarray, bool]]:
        """(ids, parity) of each text."""
        if not self.fast:
            out: list[tuple[np.ndarray, bool]] = []
            for part in _parts(texts):
                mine = self.backend.encode_batch_fast(part, add_special_tokens=False)
                others = self.other.encode(part, num_threads=self.threads)
                out += [(np.array(m.ids, np.int32), m.ids == o) for m, o in zip(mine, others, strict=True)]
            return out
        if len(self.known) > REMEMBERED_SEGMENTS:
            self.known.clear()
            self.bad.clear()
        cut = [self.segments(t) for t in texts]
        known = self.known
        new = list(dict.fromkeys(s for c in cut for s in c if s not in known))
        for at in range(0, len(new), LEARN_SEGMENTS):
            self._learn(new[at : at + LEARN_SEGMENTS])
        look = known.__getitem__
        return [(np.frombuffer(b"".join(map(look, c)), np.int32), not self.bad or self.bad.isdisjoint(c)) for c in cut]

    def decode(self, ids: np.ndarray) -> bytes:
        """Bytes of a text; the space of the dummy prefix goes."""
        return self.decode_all(ids, np.array([0, len(ids)]))[0]

    def decode_all(self, flat: np.ndarray, ends: np.ndarray) -> list[bytes]:
        """Bytes of several texts, whose ids are ``flat[ends[i] : ends[i + 1]]``."""
        made = self.surface.take(pa.array(flat, pa.int32()))
        _, offsets, data = made.buffers()
        at = np.frombuffer(offsets, np.int64)[made.offset : made.offset + len(flat) + 1][ends].tolist() if len(flat) else [0] * len(ends)
        whole = memoryview(data) if data else memoryview(b"")
        skip = self.model.add_dummy_prefix
        return [bytes(whole[i + (skip and whole[i : i + 1] == b" ") : j]) for i, j in zip(at[:-1], at[1:], strict=True)]


def _parts(texts: list[str]) -> Iterator[list[str]]:
    part, size = [], 0
    for t in texts:
        part.append(t)
        size += len(t)
        if size >= BATCH_CHARS:
            yield part
            part, size = [], 0
    if part:
        yield part


def encode_documents(docs: DataFrame, model_file: str = MODEL_FILE, id_col: str = "doc_id", text_col: str = "text") -> DataFrame:
    """(``id_col``, n_tokens, tokens, round_trip, parity) for each row.

    Null and empty texts have no token; their round trip is true.  ``round_trip``:
    the decoded bytes are the text's (a text with a literal marker or with
    characters that a model without byte fallback does not know differs).
    ``parity``: both libraries give the same ids.  Repeated rows are encoded each;
    other columns are ignored.  The model file is read once, by the driver.
    """
    limit_batches(docs.sparkSession)
    with open(model_file, "rb") as f:
        held = docs.sparkSession.sparkContext.broadcast(f.read())

    @released
    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        codec = only(("pieces", hashlib.sha1(held.value).digest()), lambda: PieceCodec(held.value))
        for batch in batches:
            for at in range(0, len(batch), SLICE_ROWS):
                part = batch.slice(at, SLICE_ROWS)
                texts = [t or "" for t in part.column(1).to_pylist()]
                done = codec.encode(texts)
                tokens = [d[0] for d in done]
                ends = np.concatenate([[0], np.cumsum([len(t) for t in tokens])]).astype(np.int64)
                flat = np.concatenate([*tokens, np.zeros(0, np.int32)])
                trip = [back == x.encode("utf-8", "surrogatepass") for back, x in zip(codec.decode_all(flat, ends), texts, strict=True)]
                lists = pa.LargeListArray.from_arrays(pa.array(ends), pa.array(flat, pa.int32())).cast(pa.list_(pa.int32()))
                yield pa.RecordBatch.from_arrays(
                    [part.column(0), pa.array(np.diff(ends)), lists, pa.array(trip, pa.bool_()), pa.array([d[1] for d in done], pa.bool_())],
                    names=["id", "n_tokens", "tokens", "round_trip", "parity"],
                )
            trim()  # the libraries' threads free in pieces

    kind = docs.schema[id_col].dataType.simpleString()
    rows = spread(docs.select(id_col, text_col)).select(F.col(id_col).alias("id"), F.col(text_col).cast("string"))
    out = rows.mapInArrow(run, f"id {kind}, n_tokens long, tokens array<int>, round_trip boolean, parity boolean")
    return out.withColumnRenamed("id", id_col)


def op6_sentencepiece_codec(spark: SparkSession, sf_dir: str) -> DataFrame:
    return encode_documents(spark.read.parquet(f"{sf_dir}/documents.parquet"))
