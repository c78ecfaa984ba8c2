"""Dialects: how a payload becomes a runtime, operand-free tokens and pieces.

A dialect holds what is special to one program form: the region before the
runtime, the region after it, the tokens that are left once operands are erased,
and the tokens that end a piece.  All are built-in column expressions, so the
whole chain is one projection.  Token strings separate tokens by one space,
except scripts, whose tokens are single letters.
"""

from __future__ import annotations

from collections.abc import Callable
from dataclasses import dataclass

from pyspark.sql import Column
from pyspark.sql import functions as F

#: Fixed values of the byte-code layout and its control flow.
DEPLOY_MARKER = "6000f300"
TRAILER_HEAD, TRAILER_END = "a165627a7a723058", "0029"
TRAILER_BYTES_BETWEEN = 33
FLOW_BREAKERS = ("56", "57", "fd", "00", "f3")
PUSH_FIRST, PUSH_COUNT = 0x60, 32


def opcode_pattern() -> str:
    """Left-to-right: a push with up to its number of operand bytes, else one byte."""
    pushes = [f"{PUSH_FIRST + i:02x}[0-9a-f]{{0,{2 * (i + 1)}}}" for i in range(PUSH_COUNT)]
    return "|".join([*pushes, ".."])


@dataclass(frozen=True)
class Dialect:
    name: str
    strip_prefix: Callable[[Column], Column]
    strip_trailer: Callable[[Column], Column]
    #: runtime, erase operands? -> token string
    tokens: Callable[[Column, bool], Column]
    #: token string -> number of tokens
    count: Callable[[Column], Column]
    #: token string -> array of pieces
    pieces: Callable[[Column], Column]
    #: pattern of a token that ends a piece
    ender: str
    #: what separates tokens
    gap: str = " "


def _same(c: Column) -> Column:
    return c


def _cut(tok: Column, enders: str, glue: str = "") -> Column:
    """Pieces that end after a token that matches ``enders``; an open tail is a piece."""
    marked = F.regexp_replace(F.concat(tok, F.lit(" ")), f"({enders}) ", "$1|")
    parts = F.transform(F.split(marked, r"\|"), lambda p: F.replace(F.trim(p), F.lit(" "), F.lit(glue)))
    return F.filter(parts, lambda p: p != "")


def _vm_prefix(c: Column) -> Column:
    return F.regexp_replace(c, f"^(?:[0-9a-f]{{2}})*?{DEPLOY_MARKER}", "")


def _vm_trailer(c: Column) -> Column:
    return F.regexp_replace(c, f"{TRAILER_HEAD}[0-9a-f]{{{2 * TRAILER_BYTES_BETWEEN}}}{TRAILER_END}$", "")


def _vm_tokens(c: Column, erase: bool) -> Column:
    found = F.regexp_extract_all(c, F.lit(opcode_pattern()), F.lit(0))
    return F.array_join(F.transform(found, lambda x: F.substring(x, 1, 2)) if erase else found, " ")


def vm_pieces(terminators: tuple[str, ...] = FLOW_BREAKERS) -> Callable[[Column], Column]:
    return lambda tok: _cut(tok, "|".join(terminators))


def _words(tok: Column) -> Column:
    return F.when(tok == "", F.lit(0)).otherwise(F.size(F.split(tok, " ")))


def _prose_tokens(c: Column, erase: bool) -> Column:
    low = F.lower(c)
    plain = F.regexp_replace(low, "[0-9]+", "") if erase else low
    blanks = F.regexp_replace(plain, "[ \t]+", " ")
    return F.trim(F.regexp_replace(blanks, "[.!?\n]+", "."))


def _prose_count(tok: Column) -> Column:
    return F.regexp_count(tok, F.lit("[^. ]+"))


def _prose_pieces(tok: Column) -> Column:
    return F.filter(F.transform(F.split(tok, r"\."), lambda p: F.trim(p)), lambda p: p != "")


def _markup_trailer(c: Column) -> Column:
    return F.regexp_replace(F.regexp_replace(c, "(?s)<!--.*?-->", ""), "(?s)<footer>.*?</footer>", "<footer></footer>")


def _markup_tokens(c: Column, erase: bool) -> Column:
    pattern = "</?[a-zA-Z][a-zA-Z0-9]*" if erase else "</?[a-zA-Z][^>]*"
    return F.array_join(F.transform(F.regexp_extract_all(c, F.lit(pattern), F.lit(0)), lambda x: F.replace(x, F.lit(" "), F.lit("_"))), " ")


def _script_tokens(c: Column, erase: bool) -> Column:
    return F.regexp_replace(c, "[^a-z]", "") if erase else c


DIALECTS = {
    "vmhex": Dialect("vmhex", _vm_prefix, _vm_trailer, _vm_tokens, _words, vm_pieces(), "(?:56|57|fd|00|f3)(?: |$)"),
    "prose": Dialect(
        "prose", _same, lambda c: F.regexp_replace(c, r"(?i)\n[^\n]*(licen[cs]e|rights reserved)[^\n]*\z", ""), _prose_tokens, _prose_count, _prose_pieces, "[.]"
    ),
    "markup": Dialect(
        "markup", lambda c: F.regexp_replace(c, "(?s)^.*?</head>", ""), _markup_trailer, _markup_tokens, _words,
        lambda tok: _cut(tok, "</(?:p|li|h1|div|nav|article|footer)", " "), "</(?:p|li|h1|div|nav|article|footer)(?: |$)",
    ),
    "script": Dialect(
        "script", _same, _same, _script_tokens, lambda tok: F.length(tok),
        lambda tok: F.filter(F.split(F.regexp_replace(tok, "([pe])", "$1|"), r"\|"), lambda p: p != ""),
        "[pe]", "",
    ),
    "rowseq": Dialect("rowseq", _same, _same, lambda c, erase: F.regexp_replace(c, ":[0-9.]*", "") if erase else c, _words, lambda tok: _cut(tok, "[A-Z]F", " "), "[A-Z]F(?: |$)"),
    "vector": Dialect("vector", _same, _same, lambda c, erase: c, _words, lambda tok: F.filter(F.split(tok, " "), lambda p: p != ""), "[01]+(?: |$)"),
}

#: Stages of pre-processing that can be left out one by one.
STAGES = ("prefix", "trailer", "operands")


def normalized_columns(payload: Column, dialect: str, stages: tuple[str, ...] = STAGES) -> dict[str, Column]:
    """runtime and tok of a payload; had_prefix and had_trailer say what was cut."""
    d = DIALECTS[dialect]
    body = d.strip_prefix(payload) if "prefix" in stages else payload
    runtime = d.strip_trailer(body) if "trailer" in stages else body
    return {
        "had_prefix": body != payload,
        "had_trailer": runtime != body,
        "runtime": runtime,
    }
