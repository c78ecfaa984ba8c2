"""Fingerprint symbols, edit distance and scores as column expressions."""

from __future__ import annotations

from pyspark.sql import Column
from pyspark.sql import functions as F

#: Fixed value: the symbols of a fingerprint.
ALPHABET = "ABCDEFGHIJKLMNOPQRSTUVWXYZabcdefghijklmnopqrstuvwxyz0123456789+/"


def piece_hash(piece: Column, algo: str = "md5", digest_chars: int = 8) -> Column:
    """Short digest of a piece as a non-negative long."""
    if algo == "md5":
        return F.conv(F.substring(F.md5(piece), 1, digest_chars), 16, 10).cast("bigint")
    if algo == "crc32":
        return F.crc32(piece)
    if algo == "xxhash64":
        return F.pmod(F.xxhash64(piece), F.lit(1 << 32))
    if algo == "fnv1a32":
        return fnv1a32(piece)
    raise ValueError(f"unknown digest {algo}")


#: Fixed values of the 32-bit FNV-1a hash.
FNV_START, FNV_PRIME = 2166136261, 16777619


def fnv1a32(text: Column) -> Column:
    """32-bit FNV-1a of the UTF-8 bytes, folded byte by byte."""
    digits = F.hex(F.encode(text, "UTF-8"))
    octets = F.filter(F.split(F.regexp_replace(digits, "(..)", "$1 "), " "), lambda x: x != "")
    step = lambda h, x: (h.bitwiseXOR(F.conv(x, 16, 10).cast("bigint")) * FNV_PRIME).bitwiseAND(F.lit(0xFFFFFFFF))
    return F.aggregate(octets, F.lit(FNV_START).cast("bigint"), step)


def symbol(number: Column) -> Column:
    return F.substr(F.lit(ALPHABET), (number % 64 + 1).cast("int"), F.lit(1))


def fingerprint(pieces: Column, algo: str = "md5", digest_chars: int = 8) -> Column:
    """A symbol for each piece, in order."""
    if algo == "md5" and digest_chars >= 2:
        # a digest modulo 64 is in its last two digits
        ends = F.transform(pieces, lambda p: F.substring(F.md5(p), digest_chars - 1, 2))
        place = lambda e, i: F.instr(F.lit("0123456789abcdef"), F.substring(e, i, 1))
        return F.array_join(F.transform(ends, lambda e: F.substr(F.lit(ALPHABET), (place(e, 1) - 1) % 4 * 16 + place(e, 2), F.lit(1))), "")
    return F.array_join(F.transform(pieces, lambda p: symbol(piece_hash(p, algo, digest_chars))), "")


def score_bp(dist: Column, max_len: Column) -> Column:
    """Similarity in basis points, on integers."""
    scaled = 10000 * (max_len - dist)
    return ((scaled - scaled % max_len) / max_len).cast("bigint")


def bound(threshold: int, max_len: str, inclusive: bool = True) -> str:
    """SQL text: largest distance that still reaches the threshold."""
    slack = f"{100 - threshold} * {max_len}"
    return f"cast(({slack}) div 100 as int)" if inclusive else f"cast(({slack} - 1) div 100 as int)"


def reaches(score: Column, threshold: int, inclusive: bool = True) -> Column:
    return score >= threshold * 100 if inclusive else score > threshold * 100
