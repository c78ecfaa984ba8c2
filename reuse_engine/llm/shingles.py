"""Words, five-word shingles and 64-bit shingle hashes of whole texts (numpy).

A word is a maximal run of bytes outside ``\\x20`` and ``\\x09-\\x0D``; only
A-Z are lower-cased.  Texts are hashed together, a few hundred kilobytes at a
time: a word's polynomial hash is a difference of running sums, so no word
becomes a Python object.  A longer text is cut at white space.
"""

from __future__ import annotations

import hashlib
import re

import numpy as np
import xxhash

WIDTH = 5
#: Bytes that are hashed together.
CHUNK_BYTES = 1 << 18

_MIX = [np.uint64(k) for k in (0x9E3779B97F4A7C15, 0xC2B2AE3D27D4EB4F, 0x165667B19E3779F9, 0x27D4EB2F165667C5, 0x85EBCA77C2B2AE63)]
_SHIFT, _HALF, _ONE = np.uint64(29), np.uint64(32), np.uint64(1)
_BASE = 0xD1342543DE82EF95  # odd, so that it has an inverse modulo 2**64
_SPACE = np.zeros(256, bool)
_SPACE[[0x20, 0x09, 0x0A, 0x0B, 0x0C, 0x0D]] = True
_LOWER = np.arange(256, dtype=np.uint64) + _ONE
_LOWER[65:91] += np.uint64(32)
_LOWER[_SPACE] = 0
_CUT = re.compile(rb"[\x20\x09-\x0D]")


class Shingler:
    """Sorted distinct shingle hashes of texts."""

    def __init__(self) -> None:
        self.power = self.inverse = np.ones(1, np.uint64)

    def _powers(self, n: int) -> None:
        if len(self.power) < n:
            size = max(n, CHUNK_BYTES + 1024)
            for name, base in (("power", _BASE), ("inverse", pow(_BASE, -1, 1 << 64))):
                steps = np.full(size, base, np.uint64)
                steps[0] = 1
                setattr(self, name, np.cumprod(steps, dtype=np.uint64))

    def _hashes(self, joined: bytes) -> tuple[np.ndarray, np.ndarray]:
        """(hash, start) of each word of bytes that end with white space."""
        raw = np.frombuffer(joined, np.uint8)
        self._powers(len(raw))
        space = _SPACE[raw]
        sums = np.cumsum(_LOWER[raw] * self.power[: len(raw)], dtype=np.uint64)
        turn = np.flatnonzero(space[1:] != space[:-1]) + 1
        if len(raw) and not space[0]:
            turn = np.concatenate([np.zeros(1, turn.dtype), turn])
        start, end = turn[0::2], turn[1::2]
        before = np.where(start > 0, sums[start - 1], np.uint64(0))
        h = (sums[end - 1] - before) * self.inverse[start]
        h = (h ^ (h >> _HALF)) * _MIX[1]
        return h ^ (h >> _SHIFT), start

    def word_hashes(self, text: bytes | None) -> np.ndarray:
        parts, at = [], 0
        text = text or b""
        while at < len(text):
            cut = _CUT.search(text, at + CHUNK_BYTES) if len(text) - at > CHUNK_BYTES else None
            end = cut.start() if cut else len(text)
            parts.append(self._hashes(text[at:end] + b" ")[0])
            at = end
        return np.concatenate(parts) if parts else np.zeros(0, np.uint64)

    def distinct(self, text: bytes | None) -> np.ndarray:
        """Sorted; a text of fewer than five words has its whole sequence as one."""
        return _distinct(self.word_hashes(text))

    def each(self, texts: list[bytes | None]) -> list[np.ndarray]:
        """:meth:`distinct` of every text, hashed together."""
        out: list[np.ndarray] = []
        held: list[bytes] = []
        size = 0

        def flush() -> None:
            nonlocal size
            if held:
                h, start = self._hashes(b" ".join(held) + b" ")
                ends = np.searchsorted(start, np.cumsum([len(t) + 1 for t in held]))
                windows = _windows(h)
                first = 0
                for last in ends.tolist():
                    n = last - first
                    out.append(np.unique(windows[first : last - WIDTH + 1]) if n >= WIDTH else _distinct(h[first:last]))
                    first = last
                held.clear()
                size = 0

        for t in texts:
            t = t or b""
            if len(t) > CHUNK_BYTES:
                flush()
                out.append(self.distinct(t))
                continue
            held.append(t)
            size += len(t) + 1
            if size >= CHUNK_BYTES:
                flush()
        flush()
        return out


def _windows(h: np.ndarray) -> np.ndarray:
    n = max(len(h) - WIDTH + 1, 0)
    s = h[:n] * _MIX[0]
    for i in range(1, WIDTH):
        s = (s ^ (s >> _SHIFT)) * _MIX[i] + h[i : n + i]
    return s ^ (s >> _SHIFT)


def _distinct(h: np.ndarray) -> np.ndarray:
    if len(h) == 0:
        return h
    if len(h) < WIDTH:
        return np.array([xxhash.xxh64_intdigest(h.tobytes(), seed=len(h))], dtype=np.uint64)
    return np.unique(_windows(h))


def set_digest(s: np.ndarray) -> bytes:
    """128 bits that name a set of shingles."""
    return hashlib.blake2b(s.tobytes(), digest_size=16).digest()
