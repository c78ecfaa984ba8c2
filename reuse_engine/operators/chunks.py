"""Candidates of a similarity threshold by chunks, without a row for each chance meeting.

With at most k = (100 - t) m div 100 edits, a text of m symbols that is cut into
k + 1 chunks keeps one chunk whole, and the shorter side holds it at a place that
those edits can reach.  Texts are dealt by length bucket and block, so that
every two that may pair meet in one cell; inside a cell the chunks of the longer
side are looked up among the substrings of the shorter one, then places and
symbol counts are tested, and what passes is measured there, many pairs at a time
(:func:`distances`).  Nothing is lost, and only pairs within the bound leave the cell.
"""

from __future__ import annotations

from collections.abc import Iterator

import numpy as np
import pandas as pd
import pyarrow as pa
import pyarrow.compute as pc
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

#: Texts and symbols of a block, about; meetings that are tested at once; cells of symbol counts.
BLOCK, BLOCK_SYMBOLS, STEP, COUNTS = 8_192, 500_000, 1 << 20, 64
#: Words of 64 rows that a step of the edit distance works on; entries of a dense table of symbols.
LANES, DENSE = 1 << 16, 1 << 22
#: Pairs for each word of 64 rows up to which whole columns as numbers beat a column of all tables at a time.
FEW = 16
_BASE = 0x9E3779B97F4A7C15
_INVERSE = pow(_BASE, -1, 1 << 64)


def edits_of(m: np.ndarray, threshold: int) -> np.ndarray:
    return (100 - threshold) * m // 100


class _Texts:
    """Texts of a block as one array of code points."""

    def __init__(self, texts: list[str]):
        self.size = np.array([len(t) for t in texts], np.int64)
        self.start = np.concatenate([[0], np.cumsum(self.size)[:-1]]).astype(np.int64)
        self.code = np.frombuffer("".join(texts).encode("utf-32-le"), np.uint32)
        powers = np.full(len(self.code) + 1, _BASE, np.uint64)
        inverse = np.full(len(self.code) + 1, _INVERSE, np.uint64)
        powers[0] = inverse[0] = 1
        powers, self.inverse = np.cumprod(powers), np.cumprod(inverse)
        self.sums = np.concatenate([np.zeros(1, np.uint64), np.cumsum((self.code.astype(np.uint64) + np.uint64(1)) * powers[:-1])])
        owner = np.repeat(np.arange(len(texts)), self.size)
        flat = np.bincount(owner * COUNTS + self.code % COUNTS, minlength=len(texts) * COUNTS) if len(texts) else np.zeros(0, np.int64)
        kind = np.uint8 if not len(flat) or flat.max() < 256 else np.uint32
        self.counts = flat.reshape(-1, COUNTS).astype(kind)

    def twos(self, width: int) -> np.ndarray:
        """Counts of neighbouring symbols of every text, in ``width`` cells of hashes."""
        owner = np.repeat(np.arange(len(self.size)), self.size)
        at = np.flatnonzero(owner[1:] == owner[:-1]) if len(owner) else np.zeros(0, np.int64)
        both = (self.code[at].astype(np.uint64) << np.uint64(32) | self.code[at + 1]) * np.uint64(_BASE) >> np.uint64(40)
        flat = np.bincount(owner[at] * width + (both % np.uint64(width)).astype(np.int64), minlength=len(self.size) * width)
        return flat.reshape(-1, width).astype(np.uint8 if not len(flat) or flat.max() < 256 else np.uint32)

    def hashes(self, at: np.ndarray, length: int) -> np.ndarray:
        """Of the substrings of one length that begin at places of the array; equal substrings have equal hashes."""
        return (self.sums[at + length] - self.sums[at]) * self.inverse[at]


def _spans(value: np.ndarray, owner: np.ndarray, place: np.ndarray) -> tuple[np.ndarray, ...]:
    """Distinct (hash, text) in order of hashes, with first and last place."""
    order = np.lexsort((place, owner, value))
    value, owner, place = value[order], owner[order], place[order]
    if not len(value):
        return value, owner, place, place
    fresh = np.flatnonzero(np.concatenate([[True], (value[1:] != value[:-1]) | (owner[1:] != owner[:-1])]))
    last = np.concatenate([fresh[1:], [len(value)]]) - 1
    return value[fresh], owner[fresh], place[fresh], place[last]


def _chunks(texts: _Texts, threshold: int) -> tuple[np.ndarray, np.ndarray, np.ndarray]:
    """(text, place, length) of the chunks of every text."""
    n = edits_of(texts.size, threshold) + 1
    owner = np.repeat(np.arange(len(n)), n)
    nth = np.arange(len(owner)) - np.repeat(np.cumsum(n) - n, n)
    size, n = texts.size[owner], n[owner]
    place = nth * size // n
    return owner, place, (nth + 1) * size // n - place


def _expand(low: np.ndarray, high: np.ndarray) -> Iterator[tuple[np.ndarray, np.ndarray]]:
    """(row, match) for all matches low..high of every row, about ``STEP`` at a time."""
    upto = np.cumsum(high - low)
    first = 0
    while first < len(low):
        base = upto[first - 1] if first else 0
        last = max(first + 1, int(np.searchsorted(upto, base + STEP, "right")))
        n = (high - low)[first:last]
        row = np.repeat(np.arange(first, last), n)
        yield row, np.arange(len(row)) - np.repeat(np.cumsum(n) - n, n) + low[row]
        first = last


def _by_chunks(ys: _Texts, xs: _Texts, threshold: int) -> Iterator[tuple]:
    """Spans of the chunks of ``ys`` and of the substrings of ``xs``, by length."""
    owner, place, length = _chunks(ys, threshold)
    holder = np.repeat(np.arange(len(xs.size)), xs.size)
    within = np.arange(len(holder)) - xs.start[holder]
    for c in np.unique(length):
        mine = length == c
        fits = np.flatnonzero(within + c <= xs.size[holder])
        yield (
            _spans(ys.hashes(ys.start[owner[mine]] + place[mine], int(c)), owner[mine], place[mine]),
            _spans(xs.hashes(fits, int(c)), holder[fits], within[fits]),
        )


def _by_keys(ys: list, xs: list) -> Iterator[tuple]:
    """Spans of given keys, which have no place."""
    sides = []
    for side in (ys, xs):
        owner = np.repeat(np.arange(len(side)), [len(k) for k in side])
        sides.append(_spans(np.concatenate([np.zeros(0, np.int64), *side]).astype(np.int64), owner, np.zeros(len(owner), np.int64)))
    yield tuple(sides)


def meetings(long: list[str], short: list[str], threshold: int, keys: tuple[list, list] | None = None) -> tuple[np.ndarray, np.ndarray]:
    """Places (in ``long``, in ``short``) of the pairs that may reach the threshold, the first at least as long.

    With ``keys`` of both sides, only pairs that share one count, instead of a chunk.
    """
    ys, xs = _Texts(long), _Texts(short)
    found = [np.zeros(0, np.int64)]
    for (yv, yo, y0, y1), (xv, xo, x0, x1) in _by_keys(*keys) if keys else _by_chunks(ys, xs, threshold):
        for row, match in _expand(np.searchsorted(xv, yv, "left"), np.searchsorted(xv, yv, "right")):
            y, x = yo[row], xo[match]
            m = ys.size[y]
            k, more = edits_of(m, threshold), m - xs.size[x]
            slack = (k - more) >> 1
            ok = (more >= 0) & (more <= k)
            if not keys:
                ok &= (y0[row] - x1[match] <= more + slack) & (y1[row] - x0[match] >= -slack)
            y, x, least = y[ok], x[ok], (m - k)[ok]
            pairs, at = np.unique(y * len(xs.size) + x, return_index=True)
            y, x, least = y[at], x[at], least[at]
            found.append(pairs[np.minimum(ys.counts[y], xs.counts[x]).sum(axis=1, dtype=np.int64) >= least])
    every = np.unique(np.concatenate(found))
    y, x = every // max(len(xs.size), 1), every % max(len(xs.size), 1)
    some = _share_twos(ys, xs, y, x, threshold)
    return y[some], x[some]


def _share_twos(ys: _Texts, xs: _Texts, y: np.ndarray, x: np.ndarray, threshold: int) -> np.ndarray:
    """True where two texts share the neighbouring symbols that the bound asks for: an edit changes two of m - 1.

    Long texts hold much the same symbols, so that their counts tell little; what follows what does.
    """
    some = np.ones(len(y), bool)
    m = ys.size[y]
    least = m - 1 - 2 * edits_of(m, threshold)
    asked = np.flatnonzero(least > 0)
    if len(asked):
        width = max(256, 1 << int(4 * ys.size.max()).bit_length())
        of_y, of_x = ys.twos(width), xs.twos(width)
        for first in range(0, len(asked), step := max(1, (1 << 24) // width)):
            at = asked[first : first + step]
            some[at] = np.minimum(of_y[y[at]], of_x[x[at]]).sum(axis=1, dtype=np.int64) >= least[at]
    return some


def _columns(ys: _Texts, yc: np.ndarray, xs: _Texts, xc: np.ndarray, i: np.ndarray, j: np.ndarray, n_symbols: int, words: int) -> np.ndarray:
    """Edit distances of pairs of which the second text takes ``words`` words of 64 rows: a column of all tables at a time.

    A column is kept as the bits of its steps up and down, so a word of additions
    and masks moves 64 rows, and a carry moves the step at its border to the next word.
    """
    sorting = np.argsort(-ys.size[i], kind="stable")
    held, p = np.unique(j[sorting], return_inverse=True)
    size = xs.size[held]
    holder = np.repeat(np.arange(len(held)), size)
    row = np.arange(len(holder)) - np.repeat(np.cumsum(size) - size, size)
    keys, at = np.unique(holder * n_symbols + xc[xs.start[held][holder] + row], return_inverse=True)
    equal = np.zeros((words, len(keys) + 1), np.uint64)  # the last one: symbols that a text does not hold
    np.bitwise_or.at(equal, (row >> 6, at), np.uint64(1) << (row & 63).astype(np.uint64))
    dense = None
    if len(held) * n_symbols <= DENSE:
        dense = np.full(len(held) * n_symbols, len(keys))
        dense[keys] = np.arange(len(keys))
    n, begin, base = ys.size[i][sorting], ys.start[i][sorting], p * n_symbols
    one, top = np.uint64(1), np.uint64(63)
    up, down = np.full((words, len(n)), ~np.uint64(0)), np.zeros((words, len(n)), np.uint64)
    end, dist = ((size[p] - 1) & 63).astype(np.uint64), size[p].astype(np.int64)
    for t in range(int(n[0]) if len(n) else 0):
        c = int(np.searchsorted(-n, -t, "left"))
        key = base[:c] + yc[begin[:c] + t]
        if dense is not None:
            found = dense[key]
        else:
            found = np.minimum(np.searchsorted(keys, key), len(keys) - 1)
            found[keys[found] != key] = len(keys)
        more, less = np.ones(c, np.uint64), np.zeros(c, np.uint64)
        for w in range(words):
            eq, pv, mv = equal[w, found], up[w, :c], down[w, :c]
            xv = eq | mv
            eq |= less
            xh = (((eq & pv) + pv) ^ pv) | eq
            ph, mh = mv | ~(xh | pv), pv & xh
            if w == words - 1:
                dist[:c] += ((ph >> end[:c]) & one).astype(np.int64) - ((mh >> end[:c]) & one).astype(np.int64)
            more, ph, less, mh = ph >> top, (ph << one) | more, mh >> top, (mh << one) | less
            up[w, :c], down[w, :c] = mh | ~(xv | ph), ph & xv
    out = np.empty(len(n), np.int64)
    out[sorting] = dist
    return out


def _whole_columns(ys: _Texts, yc: np.ndarray, xs: _Texts, xc: np.ndarray, i: np.ndarray, j: np.ndarray) -> np.ndarray:
    """As :func:`_columns`, a pair after the other: a column's steps are two numbers of as many bits as the second text has symbols.

    Long texts are few, so that a table of many words has too few pairs to share its steps.
    """
    out, held, equal, mask = np.empty(len(i), np.int64), -1, {}, 0
    for at in np.argsort(j, kind="stable"):
        if j[at] != held:
            held, equal = j[at], {}
            mask = (1 << int(xs.size[held])) - 1
            text = xc[xs.start[held] : xs.start[held] + xs.size[held]]
            order = np.argsort(text, kind="stable")
            kinds, first = np.unique(text[order], return_index=True)
            for kind, rows in zip(kinds.tolist(), np.split(order, first[1:])):
                bits = np.zeros(len(text), np.uint8)
                bits[rows] = 1
                equal[kind] = int.from_bytes(np.packbits(bits, bitorder="little").tobytes(), "little")
        begin, n = int(ys.start[i[at]]), int(ys.size[i[at]])
        up, down = mask, 0
        for c in yc[begin : begin + n].tolist():
            eq = equal.get(c, 0)
            xv = eq | down
            xh = ((((eq & up) + up) ^ up) | eq) & mask
            ph = (((down | (mask ^ (xh | up))) << 1) | 1) & mask
            up, down = (((up & xh) << 1) & mask) | (mask ^ (xv | ph)), ph & xv
        out[at] = n + up.bit_count() - down.bit_count()
    return out


def distances(ys: _Texts, xs: _Texts, i: np.ndarray, j: np.ndarray) -> np.ndarray:
    """Edit distance of text ``i`` of ``ys`` and text ``j`` of ``xs``, for every pair; no text is empty."""
    out = np.zeros(len(i), np.int64)
    symbols = np.unique(np.concatenate([ys.code, xs.code]))
    yc, xc = np.searchsorted(symbols, ys.code), np.searchsorted(symbols, xs.code)
    words = (xs.size[j] + 63) >> 6
    order = np.lexsort((j, words))
    ranked, first = words[order], 0
    while first < len(order):
        w = int(ranked[first])
        end = int(np.searchsorted(ranked, w, "right"))
        few = end - first <= FEW * w
        last = end if few else min(end, first + min(max(LANES // w, FEW * w, 64), 1 << 14))
        part = order[first:last]
        out[part] = _whole_columns(ys, yc, xs, xc, i[part], j[part]) if few else _columns(ys, yc, xs, xc, i[part], j[part], len(symbols), w)
        first = last
    return out


_CELL = "array<struct<band:int,step:int,i:int>>"


def cells(rows: DataFrame, carried: list[str], symbols: str, block: int = BLOCK) -> DataFrame:
    """``rows`` (corpus, origin, unit_id, band and more) dealt so that rows of one or of neighbour bands meet in one cell.

    Columns: ``carried``, is_long, step and cell.  With step 0 a cell holds two blocks of
    one band, and both orders of two blocks are there; with step 1 the long side is of
    the higher band.  ``symbols`` names the column that says how long a row is.
    """
    load = F.greatest(F.ceil(F.count("*") / block), F.ceil(F.sum(symbols) / BLOCK_SYMBOLS)).cast("int")
    blocks = rows.groupBy("corpus", "origin", "band").agg(load.alias("n"))
    around = blocks.join(blocks.select("corpus", "origin", (F.col("band") - 1).alias("band"), F.col("n").alias("above")), ["corpus", "origin", "band"], "left")
    around = around.join(blocks.select("corpus", "origin", (F.col("band") + 1).alias("band"), F.col("n").alias("below")), ["corpus", "origin", "band"], "left")
    own = F.pmod(F.xxhash64("unit_id"), F.col("n")).cast("int")
    dealt = rows.join(F.broadcast(around), ["corpus", "origin", "band"]).withColumn("own", own)
    cell = lambda of, to, shift: F.transform(F.sequence(F.lit(0), F.col(of) - 1), lambda i: F.struct(to.alias("band"), shift.alias("step"), i.alias("i")))
    zero, one, none = F.lit(0), F.lit(1), F.array().cast(_CELL)
    as_long = F.concat(cell("n", F.col("band"), zero), F.coalesce(cell("below", F.col("band"), one), none))
    as_short = F.concat(cell("n", F.col("band"), zero), F.coalesce(cell("above", F.col("band") + 1, one), none))
    long = dealt.select(*carried, F.lit(True).alias("is_long"), "own", F.explode(as_long).alias("c")).select("*", F.col("own").alias("row"), F.col("c.i").alias("col"))
    short = dealt.select(*carried, F.lit(False).alias("is_long"), "own", F.explode(as_short).alias("c")).select("*", F.col("c.i").alias("row"), F.col("own").alias("col"))
    both = long.unionByName(short).select(*carried, "is_long", "c.step", F.concat_ws(":", "corpus", "origin", "c.band", "c.step", "row", "col").alias("cell"))
    # a few bytes of a cell can be much work, so small cells must not be put together by their bytes
    return both.repartition(int(rows.sparkSession.conf.get("spark.sql.shuffle.partitions")), "cell")


def chunk_pairs(texts: DataFrame, threshold: int, bucket, keyed: bool = False, sided: bool = False) -> DataFrame:
    """(corpus, origin, a, b, dist): every two of ``texts`` (corpus, origin, unit_id, fp, fp_len) that reach the threshold.

    ``bucket`` maps a length to a bucket so that lengths that may pair lie in one or in neighbours.
    ``keyed``: ``texts`` has an array ``keys`` too, and only pairs that share a key count.
    ``sided``: ``texts`` has booleans ``old`` and ``new`` too, and only pairs of a new and an old text count.
    """
    carried = ["corpus", "origin", "unit_id", "fp", *(["keys"] if keyed else []), *(["old", "new"] if sided else [])]
    both = cells(texts.select(*carried, "fp_len", bucket(F.col("fp_len")).alias("band")), carried, "fp_len")

    def meet(pdf: pd.DataFrame) -> pd.DataFrame:
        y, x = pdf[pdf["is_long"]], pdf[~pdf["is_long"]]
        i, j = meetings(list(y["fp"]), list(x["fp"]), threshold, (list(y["keys"]), list(x["keys"])) if keyed else None)
        ids_y, ids_x = y["unit_id"].to_numpy()[i], x["unit_id"].to_numpy()[j]
        ys, xs = _Texts(list(y["fp"])), _Texts(list(x["fp"]))
        keep = (ids_x < ids_y) | (ys.size[i] != xs.size[j])  # texts of one length meet twice, or themselves
        if sided:
            mark = lambda side, at, c: side[c].to_numpy(bool)[at]
            keep &= (mark(y, i, "new") & mark(x, j, "old")) | (mark(y, i, "old") & mark(x, j, "new"))
        i, j, ids_y, ids_x = i[keep], j[keep], ids_y[keep], ids_x[keep]
        dist = distances(ys, xs, i, j)
        near = dist <= edits_of(ys.size[i], threshold)
        ids_y, ids_x = ids_y[near], ids_x[near]
        swap = ids_x < ids_y
        out = {"corpus": pdf["corpus"].iloc[0], "origin": pdf["origin"].iloc[0], "a": np.where(swap, ids_x, ids_y), "b": np.where(swap, ids_y, ids_x), "dist": dist[near]}
        return pd.DataFrame(out, columns=list(out))

    return both.groupBy("cell").applyInPandas(meet, "corpus string, origin string, a string, b string, dist int")


#: Pairs of members that leave a cell at once.
OUT = 1 << 18


def _by_cell(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.Table]:
    """A table for each cell of rows sorted by cell."""
    held, name = [], None
    for batch in batches:
        at = np.array(batch.column("cell").to_pylist(), object)
        cuts = [0, *(np.flatnonzero(at[1:] != at[:-1]) + 1).tolist(), len(at)]
        for low, high in zip(cuts, cuts[1:]):
            if low == high:
                continue
            if held and at[low] != name:
                yield pa.Table.from_batches(held)
                held = []
            name = at[low]
            held.append(batch.slice(low, high - low))
    if held:
        yield pa.Table.from_batches(held)


def _lists(column: pa.ChunkedArray) -> tuple[np.ndarray, np.ndarray, pa.Array]:
    """(start, length, values) of a column of arrays."""
    size = pc.fill_null(pc.list_value_length(column), 0).to_numpy().astype(np.int64)
    flat = pc.list_flatten(column)
    return np.cumsum(size) - size, size, flat.combine_chunks() if isinstance(flat, pa.ChunkedArray) else flat


def member_pairs(groups: DataFrame, threshold: int, bucket, attributes: list[str], keyed: bool = False, whole: bool = False) -> DataFrame:
    """Every two members of ``groups`` whose texts reach the threshold, with fp_len, ``attributes`` (and fp, if ``whole``) of both and dist.

    A group (corpus, origin, unit_id, fp, fp_len) has arrays ``ids`` and ``attributes`` of its members.
    Members travel with their text, so a pair is made in its cell, some at a time, and is never dealt again.
    """
    carried = ["corpus", "origin", "unit_id", "fp", "ids", *attributes, *(["keys"] if keyed else [])]
    load = groups.withColumn("__load", F.col("fp_len") + F.size("ids"))
    both = cells(load.select(*carried, "__load", bucket(F.col("fp_len")).alias("band")), carried, "__load").sortWithinPartitions("cell")

    def pairs_of_cell(t: pa.Table) -> Iterator[pa.RecordBatch]:
        is_long = t.column("is_long")
        y, x = t.filter(is_long), t.filter(pc.invert(is_long))
        fp_y, fp_x = y.column("fp").to_pylist(), x.column("fp").to_pylist()
        i, j = meetings(fp_y, fp_x, threshold, tuple([np.array(k, np.int64) for k in side.column("keys").to_pylist()] for side in (y, x)) if keyed else None)
        id_y, id_x = (np.array(side.column("unit_id").to_pylist(), object) for side in (y, x))
        ys, xs = _Texts(fp_y), _Texts(fp_x)
        keep = ((id_x[j] <= id_y[i]) | (ys.size[i] != xs.size[j])).astype(bool)  # texts of one length meet twice
        i, j = i[keep], j[keep]
        dist = distances(ys, xs, i, j)
        near = dist <= edits_of(ys.size[i], threshold)
        i, j, dist = i[near], j[near], dist[near]
        same = (id_x[j] == id_y[i]).astype(bool)
        (at_y, n_y, flat_y), (at_x, n_x, flat_x) = _lists(y.column("ids")), _lists(x.column("ids"))
        ids = pa.concat_arrays([flat_y, flat_x])
        rank = pc.rank(ids, tiebreaker="min").to_numpy()
        extra = {c: np.concatenate([_lists(side.column(c))[2].to_numpy(zero_copy_only=False) for side in (y, x)]) for c in attributes}
        fps = pa.array([*fp_y, *fp_x], pa.string())
        upto = np.cumsum(n_y[i] * n_x[j])
        for first in range(0, int(upto[-1]) if len(upto) else 0, OUT):
            nth = np.arange(first, min(first + OUT, int(upto[-1])))
            r = np.searchsorted(upto, nth, "right")
            nth -= upto[r] - n_y[i[r]] * n_x[j[r]]
            u, v = at_y[i[r]] + nth // n_x[j[r]], len(flat_y) + at_x[j[r]] + nth % n_x[j[r]]
            once = ~same[r] | (rank[v] < rank[u])
            r, u, v = r[once], u[once], v[once]
            swap = rank[v] < rank[u]
            a, b = np.where(swap, v, u), np.where(swap, u, v)
            size_y, size_x = ys.size[i[r]].astype(np.int32), xs.size[j[r]].astype(np.int32)
            out = {
                "corpus": pa.repeat(t.column("corpus")[0], len(r)), "origin": pa.repeat(t.column("origin")[0], len(r)),
                "unit_id_a": ids.take(pa.array(a)), "unit_id_b": ids.take(pa.array(b)),
                "fp_len_a": pa.array(np.where(swap, size_x, size_y)), "fp_len_b": pa.array(np.where(swap, size_y, size_x)),
                "dist": pa.array(dist[r].astype(np.int32)),
            }
            for c, value in extra.items():
                out |= {f"{c}_a": pa.array(value[a], pa.int64()), f"{c}_b": pa.array(value[b], pa.int64())}
            if whole:
                of_y, of_x = i[r], len(fp_y) + j[r]
                out |= {"fp_a": fps.take(pa.array(np.where(swap, of_x, of_y))), "fp_b": fps.take(pa.array(np.where(swap, of_y, of_x)))}
            yield pa.RecordBatch.from_pydict(out)

    def meet(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for t in _by_cell(batches):
            yield from pairs_of_cell(t)

    schema = "corpus string, origin string, unit_id_a string, unit_id_b string, fp_len_a int, fp_len_b int, dist int"
    schema += "".join(f", {c}_a long, {c}_b long" for c in attributes) + (", fp_a string, fp_b string" if whole else "")
    return both.mapInArrow(meet, schema)


#: Pairs of a block of :func:`text_distances`, about; blocks of a side at most.
PAIRS, SIDES = 5_000, 64


def text_distances(pairs: DataFrame, texts: DataFrame) -> DataFrame:
    """``pairs`` (origin, a, b and more) with full_dist and full_len of the texts (origin, id, text) of both ends.

    Both ends are dealt over a grid, so a text is sent once to each block of its row and
    column and not once for each pair.
    """
    n = int(min(SIDES, max(1, -(-pairs.count() // PAIRS)) ** 0.5 + 1))
    of = lambda c: F.pmod(F.xxhash64("origin", c), F.lit(n)).cast("int")
    every = F.explode(F.sequence(F.lit(0), F.lit(n - 1)))
    met = pairs.select("*", F.concat_ws(":", of("a"), of("b")).alias("cell"))
    held = texts.select("origin", "id", "text", of("id").alias("own"), every.alias("other"))
    rows, cols = (held.select("origin", "id", "text", "own", "other", F.concat_ws(":", *at).alias("cell")) for at in (("own", "other"), ("other", "own")))
    parts = int(pairs.sparkSession.conf.get("spark.sql.shuffle.partitions"))
    sent = rows.unionByName(cols.where("own <> other")).repartition(parts, "cell")
    schema = ", ".join(f"{f.name} {f.dataType.simpleString()}" for f in pairs.schema) + ", full_dist long, full_len long"

    def measure(left: pd.DataFrame, right: pd.DataFrame) -> pd.DataFrame:
        if not len(left):
            return pd.DataFrame({c: left[c] for c in left.columns if c != "cell"} | {"full_dist": [], "full_len": []})
        place = {(o, u): k for k, (o, u) in enumerate(zip(right["origin"], right["id"]))}
        both = _Texts(list(right["text"]))
        i, j = (np.array([place[o, u] for o, u in zip(left["origin"], left[s])], np.int64) for s in ("a", "b"))
        longer, dist = np.maximum(both.size[i], both.size[j]), np.maximum(both.size[i], both.size[j])
        some = (both.size[i] > 0) & (both.size[j] > 0)
        dist[some] = distances(both, both, i[some], j[some])
        return left.drop(columns="cell").assign(full_dist=dist, full_len=longer)

    return met.repartition(parts, "cell").groupBy("cell").cogroup(sent.groupBy("cell")).applyInPandas(measure, schema)


#: Rows of a block of :func:`compared`, about.
COMPARED = 4_096


def compared(rows: DataFrame, carried: list[str], by: str, ratio: int, bucket, fold, schema: str) -> DataFrame:
    """What ``fold`` makes in each cell of all pairs of ``rows`` whose lesser ``by`` is at least ``ratio`` percent of the greater one.

    ``fold`` takes both sides (with ``carried``, unit_id and ``by``) and an iterator of places
    (in the first, in the second), about ``STEP`` pairs at a time; every pair is given once and
    none of them is a row.  corpus and origin are added to the columns of ``schema``.
    """
    held = list(dict.fromkeys(["corpus", "origin", "unit_id", by, *carried]))
    dealt = cells(rows.select(*held, bucket(F.col(by)).alias("band"), F.lit(1).alias("__load")), held, "__load", COMPARED)

    def meet(pdf: pd.DataFrame) -> pd.DataFrame:
        rank = np.unique(pdf["unit_id"].to_numpy(object), return_inverse=True)[1]
        long = pdf["is_long"].to_numpy(bool)
        y, id_y = pdf[long].reset_index(drop=True), rank[long]
        order = np.argsort(pdf[by].to_numpy(np.int64)[~long], kind="stable")
        x, id_x = pdf[~long].iloc[order].reset_index(drop=True), rank[~long][order]
        of_y, of_x = y[by].to_numpy(np.int64), x[by].to_numpy(np.int64)

        def pairs() -> Iterator[tuple[np.ndarray, np.ndarray]]:
            for i, j in _expand(np.searchsorted(of_x, -(-ratio * of_y // 100), "left"), np.searchsorted(of_x, of_y, "right")):
                once = (of_x[j] < of_y[i]) | (id_x[j] < id_y[i])
                yield i[once], j[once]

        made = fold(y, x, pairs())
        return made.assign(corpus=pdf["corpus"].iloc[0], origin=pdf["origin"].iloc[0])

    return dealt.groupBy("cell").applyInPandas(meet, f"{schema}, corpus string, origin string")


def common_symbols(ys: list[str], xs: list[str]):
    """A function of places (in ``ys``, in ``xs``): symbols that both texts hold, as often as both do."""
    sizes = np.array([len(t) for t in [*ys, *xs]], np.int64)
    kinds, code = np.unique(np.frombuffer("".join([*ys, *xs]).encode("utf-32-le"), np.uint32), return_inverse=True)
    flat = np.bincount(np.repeat(np.arange(len(sizes)), sizes) * len(kinds) + code, minlength=len(sizes) * len(kinds))
    counts = flat.reshape(len(sizes), -1).astype(np.uint8 if not len(flat) or flat.max() < 256 else np.uint32)

    def common(i: np.ndarray, j: np.ndarray) -> np.ndarray:
        out = np.empty(len(i), np.int64)
        for first in range(0, len(i), part := max(1, (1 << 22) // max(len(kinds), 1))):
            at = slice(first, first + part)
            out[at] = np.minimum(counts[i[at]], counts[len(ys) + j[at]]).sum(axis=1, dtype=np.int64)
        return out

    return common
