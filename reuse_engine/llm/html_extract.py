"""HTML extraction: page structure, and a suffix array per host for boilerplate.

Each page is cut into blocks at block-level tags.  Scripts, styles, menus,
headers, footers, sidebars, adverts, notices, forms and reader comments go by
element, role or class.  Blocks inside the article (or main) element are
``sure`` and are the main text, whole; where a page has none, blocks are
``open`` and the host decides.

The token streams of a host's pages are concatenated, with a separator that
occurs once after each block.  Their suffixes are sorted by prefix doubling until
all differ, and the common prefix of neighbours is read from the ranks of each
doubling.  Neighbours that share at least ``MIN_RUN`` tokens form groups: their
shared prefixes are the repeated substrings, of any length, and each group's
distinct pages are counted.  Runs on ``MIN_PAGES`` distinct pages are covered;
open blocks lose what is covered and keep unique runs.  A page without any unique
run is a copy of others, not boilerplate, and is left whole.

A host of more than ``CHUNK_PAGES`` pages is dealt into chunks by a hash of the page
id, each with its own suffix array, and pages are counted over the host: every
chunk gives a row per distinct run of ``MIN_RUN`` tokens, by its hash, and these are
summed; a longer repeat is covered by its runs of that length.  The result does
not depend on the chunks.  A large host without open blocks has nothing to count.
"""

from __future__ import annotations

import html as entities
import re
from collections import Counter
from collections.abc import Iterator
from hashlib import blake2b

import numpy as np
import pandas as pd
import pyarrow as pa
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from reuse_engine.llm.worker_cache import limit_batches, released
from reuse_engine.storage import materialize, spread

MIN_RUN = 6
MIN_PAGES = 4
#: Pages of a host that one suffix array spans, about.
CHUNK_PAGES = 256
#: Repeated windows of large hosts that are put into the plan; beyond it they are joined.
INLINE_WINDOWS = 20_000
#: Hosts that may be broadcast.
BROADCAST_HOSTS = 1_000_000

#: Elements whose content is no markup, elements without text of their own, elements outside the main text, block-level elements.
_RAW = {"script", "style", "textarea", "title", "iframe", "noscript", "noembed", "noframes", "xmp"}
_SILENT = _RAW | {"template", "svg", "math", "object", "canvas", "head", "select", "audio", "video", "map"}
_OUTSIDE = {"nav", "header", "footer", "aside", "form", "button", "dialog", "menu", "fieldset", "label", "input"}
_BLOCK = {
    "p", "div", "h1", "h2", "h3", "h4", "h5", "h6", "li", "ul", "ol", "dl", "dt", "dd", "blockquote", "pre", "table", "thead", "tbody", "tr", "td", "th",
    "article", "main", "section", "figure", "figcaption", "hr", "address", "body", "html", "details", "summary", "caption",
} | _OUTSIDE
_VOID = {"br", "hr", "img", "input", "meta", "link", "area", "base", "col", "embed", "source", "track", "wbr"}
_MAIN = {"article", "main"}
#: Words that name what is not main text, and words that may stand beside them in a class or id.
_CORE = {
    "ad", "ads", "advert", "adverts", "advertisement", "advertisements", "advertising", "sponsor", "sponsored", "sponsors", "promo", "promos", "promotion", "banner", "banners",
    "sidebar", "sidebars", "menu", "menus", "nav", "navbar", "navigation", "breadcrumb", "breadcrumbs", "footer", "masthead", "header", "cookie", "cookies", "consent", "gdpr",
    "notice", "notices", "alert", "popup", "modal", "newsletter", "subscribe", "signup", "login", "comment", "comments", "disqus", "replies", "respond", "pagination", "toolbar",
}
_BESIDE = {
    "site", "page", "main", "top", "bottom", "left", "right", "global", "primary", "secondary", "box", "block", "container", "wrapper", "wrap", "list", "area", "section", "slot", "unit",
    "item", "items", "inner", "outer", "body", "content", "text", "bar", "links", "user", "users", "reader", "readers", "thread", "form", "buttons", "google", "js", "the", "and", "policy",
}
_BESIDE_HEADER = {"header", "masthead", "banner", "site", "top", "global", "bar", "container", "wrapper"}
_WORDS = re.compile(r"[A-Za-z]+")
_HUMP = re.compile(r"(?<=[a-z])(?=[A-Z])")
_HIDDEN = re.compile(r"display\s*:\s*none|visibility\s*:\s*hidden", re.I)
_ROLES = {"navigation", "banner", "contentinfo", "complementary", "search", "form", "dialog", "alert", "alertdialog", "menu", "menubar", "toolbar"}
_NAME = re.compile(r"[A-Za-z][^\s/>]*")
_STOP = re.compile(r"[\"'<>]")
_ATTRIBUTE = re.compile(r"([^\s\"'<>/=]+)(?:\s*=\s*(?:\"([^\"]*)\"|'([^']*)'|([^\s\"'<>]+)))?")
_COMMENT_END = re.compile(r"--!?>")
_WHITE = re.compile(r"\s+")
_ENDS_ITSELF = {"p", "li", "tr", "td", "th", "dt", "dd", "h1", "h2", "h3", "h4", "h5", "h6"}


def is_boilerplate_name(name: str) -> bool:
    """True for a class or id that names something other than main text as a whole.

    Every word of it must be known: ``cookie-notice`` is one, ``share-price`` is not.
    """
    words = [w.lower() for w in _WORDS.findall(_HUMP.sub(" ", name))]
    if "header" in words:
        return all(w in _BESIDE_HEADER for w in words)
    return bool(words) and any(w in _CORE for w in words) and all(w in _CORE or w in _BESIDE for w in words)


class _Scanner:
    """Markup of a page in order, each character looked at a bounded number of times.

    What is not closed is text: a ``<`` without a tag behind it, and a tag that
    another ``<`` interrupts.  A comment that never ends ends at the next ``>``.
    """

    def __init__(self, source: str) -> None:
        self.source = source
        self.last = source.rfind(">")
        self.missing = {'"': False, "'": False, "-->": False, "]]>": False}

    def _find(self, what: str, at: int) -> int:
        """Place of ``what`` from ``at`` on; a failed search is not made again."""
        if self.missing[what]:
            return -1
        if what == "-->":
            m = _COMMENT_END.search(self.source, at)
            found = m.end() if m else -1
        else:
            found = self.source.find(what, at)
            found += len(what) if found >= 0 and len(what) > 1 else 0
        self.missing[what] = found < 0
        return found

    def _tag_end(self, at: int) -> int:
        """Place of the ``>`` that ends the tag whose attributes start at ``at``; -1 if there is none."""
        source = self.source
        while m := _STOP.search(source, at):
            c, at = m.group(), m.end()
            if c == ">":
                return m.start()
            if c == "<":
                return -1
            if source[max(0, m.start() - 8) : m.start()].rstrip()[-1:] == "=":
                end = self._find(c, at)
                at = end + 1 if end >= 0 else at
        return -1

    def __iter__(self) -> Iterator[tuple[str, str, str]]:
        """("text", text, ""), ("open", name, attributes) and ("close", name, "")."""
        source, at, text_from = self.source, 0, 0
        while at <= self.last and (lt := source.find("<", at)) >= 0:
            end, event = -1, None
            ahead = source[lt + 1 : lt + 2]
            if source.startswith("<!--", lt):
                end = self._find("-->", lt + 2)
                end = end if end >= 0 else source.find(">", lt) + 1 or -1
            elif source.startswith("<![CDATA[", lt):
                end = self._find("]]>", lt)
                end = end if end >= 0 else source.find(">", lt) + 1 or -1
            elif ahead in ("!", "?"):
                end = source.find(">", lt) + 1 or -1
            elif ahead == "/" and (m := _NAME.match(source, lt + 2)):
                stop = self._tag_end(m.end())
                if stop >= 0:
                    end, event = stop + 1, ("close", m.group().lower(), "")
            elif m := _NAME.match(source, lt + 1):
                stop = self._tag_end(m.end())
                if stop >= 0:
                    end, event = stop + 1, ("open", m.group().lower(), source[m.end() : stop])
            if end < 0:
                at = lt + 1
                continue
            if lt > text_from:
                yield "text", source[text_from:lt], ""
            if event:
                yield event
                if event[0] == "open" and event[1] in _RAW and not event[2].endswith("/"):
                    closing = re.compile(f"</{re.escape(event[1])}(?=[\\s/>]|$)", re.I).search(source, end)
                    end = closing.start() if closing else len(source)
            at = text_from = end
        if text_from < len(source):
            yield "text", source[text_from:], ""


def _read_attributes(raw: str) -> dict[str, str]:
    found: dict[str, str] = {}
    for k, a, b, c in _ATTRIBUTE.findall(raw):
        found.setdefault(k.lower(), a or b or c)
    return found


def _verdict(name: str, raw: str) -> tuple[bool, bool]:
    """(text is dropped, is main) of an element.  Names of inline elements say nothing: code listings mark their comments so."""
    if name in _OUTSIDE or name in _SILENT:
        return True, False
    if not raw or raw.isspace():
        return False, name in _MAIN
    given = _read_attributes(raw)
    role = given.get("role", "").strip().lower()
    whole = (name in _BLOCK or name == "ins" or "-" in name) and name not in ("html", "body", "main") and role != "main"
    named = whole and any(is_boilerplate_name(n) for n in f"{given.get('class', '')} {given.get('id', '')}".split())
    hidden = "hidden" in given and given["hidden"].lower() not in ("false", "until-found")
    hidden = hidden or given.get("aria-hidden", "").lower() == "true" or bool(_HIDDEN.search(given.get("style", "")))
    dropped = named or hidden or role in _ROLES
    return dropped, not dropped and (name in _MAIN or role in ("main", "article"))


def blocks_of(page: str | None) -> list[tuple[str, int]]:
    """(text, sure) of each block that may be main text, in page order."""
    inside: list[str] = []
    outer: list[str] = []
    stack: list[tuple[str, bool, bool]] = []  # element, drops its text, is main
    opened: Counter[str] = Counter()
    held: list[str] = []
    drops = mains = 0

    def close_block() -> None:
        if held:
            text = _WHITE.sub(" ", entities.unescape("".join(held))).strip()
            held.clear()
            if text and not drops:
                (inside if mains else outer).append(text)

    def leave(name: str, within_block: bool) -> None:
        """Close the innermost open element of that name, and what is open in it."""
        nonlocal drops, mains
        if not opened[name]:
            return
        i = len(stack) - 1
        while stack[i][0] != name:
            if within_block and stack[i][0] in _BLOCK and stack[i][0] != "p":
                return
            i -= 1
        for other, dropped, main in stack[i:]:
            drops -= dropped
            mains -= main
            opened[other] -= 1
        del stack[i:]

    for kind, name, attributes in _Scanner(page or ""):
        if kind == "text":
            if not drops:
                held.append(name)
            continue
        if name in _BLOCK:
            close_block()
        elif name == "br":
            held.append(" ")
        if kind == "close":
            leave(name, False)
            continue
        if name in _VOID or attributes.rstrip().endswith("/"):
            continue
        if name in _ENDS_ITSELF:
            leave(name, True)
        dropped, main = _verdict(name, attributes)
        if main and name not in _BLOCK:
            close_block()
        stack.append((name, dropped, main))
        opened[name] += 1
        drops += dropped
        mains += main
    close_block()
    return [(t, 1) for t in inside] or [(t, 0) for t in outer]


def suffix_array(tokens: np.ndarray) -> tuple[np.ndarray, np.ndarray]:
    """Order of all suffixes, and the tokens that each shares with the one before it.

    Prefix doubling: the rank of a suffix by its first 2k tokens is that of the
    pair of ranks by k tokens at its start and k further on, until all differ.  The
    common prefix of neighbours is read from the ranks of all doublings, from the
    longest step down.
    """
    n = len(tokens)
    ranks = [np.unique(tokens, return_inverse=True)[1].astype(np.int64)]
    k = 1
    while int(ranks[-1].max(initial=0)) + 1 < n:
        ahead = np.full(n, -1, np.int64)
        ahead[: max(n - k, 0)] = ranks[-1][k:]
        ranks.append(np.unique(ranks[-1] * (n + 1) + ahead + 1, return_inverse=True)[1].astype(np.int64))
        k *= 2
    order = np.argsort(ranks[-1], kind="stable")
    shared = np.zeros(n, np.int64)
    a, b = order[:-1].copy(), order[1:].copy()
    for level in range(len(ranks) - 1, -1, -1):
        inside = np.maximum(a, b) < n
        same = np.zeros(len(a), bool)
        same[inside] = ranks[level][a[inside]] == ranks[level][b[inside]]
        step = same.astype(np.int64) << level
        a += step
        b += step
        shared[1:] += step
    return order, shared


def window_pages(streams: list[list[list[int]]], min_run: int = MIN_RUN) -> list[list[np.ndarray]]:
    """Per page and block: the number of distinct pages that hold the run of ``min_run`` tokens at each place."""
    flat: list[int] = []
    owner: list[int] = []
    spans: list[tuple[int, int, int]] = []
    for p, page in enumerate(streams):
        for tokens in page:
            spans.append((p, len(flat), len(tokens)))
            flat += tokens
            flat.append(-1 - len(spans))  # a separator that occurs once
            owner += [p] * (len(tokens) + 1)
    pages_at = np.zeros(len(flat), np.int64)
    if len(flat) >= min_run:
        order, shared = suffix_array(np.array(flat, np.int64))
        group = np.cumsum(shared < min_run) - 1  # neighbours with a long common prefix
        own = np.array(owner, np.int64)[order]
        pairs = np.unique(group * len(streams) + own) // len(streams)  # distinct (group, page)
        pages_at[order] = np.bincount(pairs, minlength=int(group[-1]) + 1)[group]
    out: list[list[np.ndarray]] = [[] for _ in streams]
    for p, at, n in spans:
        out[p].append(pages_at[at : at + max(n - min_run + 1, 0)])
    return out


def window_keys(pages: list[list[str]], min_run: int = MIN_RUN) -> list[list[np.ndarray]]:
    """Per page and block: a hash of each window of ``min_run`` tokens, the same in every chunk."""
    known: dict[str, int] = {}
    out = []
    for page in pages:
        keys = []
        for text in page:
            words = text.split(" ")
            for w in words:
                if w not in known:
                    known[w] = int.from_bytes(blake2b(w.encode("utf-8", "surrogatepass"), digest_size=8).digest(), "little")
            h = np.array([known[w] for w in words], np.uint64)
            n = max(len(h) - min_run + 1, 0)
            key = np.zeros(n, np.uint64)
            for k in range(min_run if n else 0):
                key = key * np.uint64(0x9E3779B97F4A7C15) + h[k : k + n]
            keys.append(key.view(np.int64))
        out.append(keys)
    return out


def _streams(pages: list[list[str]]) -> list[list[list[int]]]:
    known: dict[str, int] = {}
    return [[[known.setdefault(w, len(known)) for w in text.split(" ")] for text in page] for page in pages]


def clean_page(page: list[tuple[str, int]], counts: list[np.ndarray], min_run: int = MIN_RUN) -> str:
    """Main text of a page, from the number of the host's pages that hold each run of its blocks."""
    kept = []
    for (text, sure), n in zip(page, counts, strict=True):
        start = np.flatnonzero(n >= MIN_PAGES)
        if sure or not len(start):
            kept.append(text)
            continue
        words = text.split(" ")
        hit = np.zeros(len(words) + 1, np.int64)
        hit[start] += 1
        hit[start + min_run] -= 1
        cover = np.cumsum(hit[:-1]) > 0
        left = " ".join(w for w, c in zip(words, cover, strict=True) if not c)
        if left:
            kept.append(left)
    return "\n\n".join(kept or (t for t, _ in page))


_BLOCKS = "id long, url string, host string, texts array<string>, sure array<int>"
_TEXTS = "page_id long, url string, text string, n_chars long"


@released
def _parse(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
    """Rows of (id, url, host, html) with blocks for html."""
    for batch in batches:
        found = [blocks_of(h) for h in batch.column(3).to_pylist()]
        texts = pa.array([[t for t, _ in f] for f in found], pa.list_(pa.string()))
        sure = pa.array([[s for _, s in f] for f in found], pa.list_(pa.int32()))
        yield pa.RecordBatch.from_arrays([*batch.columns[:3], texts, sure], names=["id", "url", "host", "texts", "sure"])


def _out(pdf: pd.DataFrame, texts: list[str]) -> pd.DataFrame:
    return pd.DataFrame({"page_id": pdf["id"].astype("Int64"), "url": pdf["url"], "text": texts, "n_chars": pd.Series([len(t) for t in texts], index=pdf.index, dtype="int64")})


def _clean(pdf: pd.DataFrame) -> pd.DataFrame:
    """Pages of one host that is one chunk."""
    pdf = pdf.sort_values("id", kind="stable")
    counts = window_pages(_streams([list(t) for t in pdf["texts"]]))
    return _out(pdf, [clean_page(list(zip(t, s, strict=True)), n) for t, s, n in zip(pdf["texts"], pdf["sure"], counts, strict=True)])


def _windows(pdf: pd.DataFrame) -> pd.DataFrame:
    """Distinct runs of a chunk of a large host, and the pages of the chunk that hold each."""
    pages = [list(t) for t in pdf["texts"]]
    keys = [k for page in window_keys(pages) for k in page]
    counts = [n for page in window_pages(_streams(pages)) for n in page]
    windows, n = np.zeros(0, np.int64), np.zeros(0, np.int64)
    if keys:
        windows, first = np.unique(np.concatenate(keys), return_index=True)
        n = np.concatenate(counts)[first]
    size = len(windows)
    return pd.DataFrame({"host": pd.Series([pdf["host"].iloc[0]] * size, dtype=object), "chunk": np.full(size, pdf["chunk"].iloc[0], np.int64), "window": windows, "n": n})


def _totals_of(page: list[str], windows: np.ndarray, totals: np.ndarray) -> list[np.ndarray]:
    """Host totals of a page's windows, from sorted ``windows``; 0 for one that is not among them."""
    out = []
    for keys in window_keys([page])[0]:
        at = np.minimum(np.searchsorted(windows, keys), len(windows) - 1)
        out.append(np.where(windows[at] == keys, totals[at], 0))
    return out


def _clean_by_totals(pdf: pd.DataFrame, repeats: dict[str, tuple[np.ndarray, np.ndarray]]) -> pd.DataFrame:
    """Pages of large hosts, by the host totals of repeated windows; a host without any has nothing to remove."""
    texts = []
    for host, t, s in zip(pdf["host"], pdf["texts"], pdf["sure"], strict=True):
        open_page = len(s) > 0 and not s[0]
        texts.append(clean_page(list(zip(t, s, strict=True)), _totals_of(list(t), *repeats[host])) if open_page and host in repeats else "\n\n".join(t))
    return _out(pdf, texts)


def _clean_chunk(pdf: pd.DataFrame, found: pd.DataFrame) -> pd.DataFrame:
    return _clean_by_totals(pdf, _by_host(found))


def _by_host(found: pd.DataFrame) -> dict[str, tuple[np.ndarray, np.ndarray]]:
    found = found.sort_values("window")
    return {h: (p["window"].to_numpy(np.int64), p["total"].to_numpy(np.int64)) for h, p in found.groupby("host")}


def host_of(url):
    """Lower-case host of a URL column without ``www.``; no host gives the empty string."""
    return F.regexp_replace(F.regexp_extract(F.lower(F.coalesce(url, F.lit(""))), r"^[a-z][a-z0-9+.-]*://([^/?#:]*)", 1), r"^www\.", "")


def extract_pages(pages: DataFrame, chunk_pages: int = CHUNK_PAGES) -> DataFrame:
    """(page_id, url, text, n_chars) for each row of ``pages`` (page_id, url, html).

    Null or empty html, and pages without main text, give the empty string.  A
    null url is a host of its own kind.  Repeated rows are extracted each.  Other
    columns are ignored; an empty table gives an empty result.
    """
    limit_batches(pages.sparkSession)
    rows = pages.select(F.col("page_id").cast("long").alias("id"), "url", host_of(F.col("url")).alias("host"), "html")
    sizes = rows.groupBy("host").agg(F.count("*").alias("pages"))
    large = materialize(sizes.where(F.col("pages") > chunk_pages), "html-hosts")
    few = _few(large)
    small = spread(rows).join(few.select("host"), "host", "left_anti").select("id", "url", "host", "html").mapInArrow(_parse, _BLOCKS)
    out = small.groupBy("host").applyInPandas(_clean, _TEXTS)
    return out.unionByName(_extract_large(rows, few, chunk_pages)) if large.head(1) else out


def _few(df: DataFrame) -> DataFrame:
    return F.broadcast(df) if df.count() <= BROADCAST_HOSTS else df


def _extract_large(rows: DataFrame, large: DataFrame, chunk_pages: int) -> DataFrame:
    """Pages of hosts of many chunks, by counts over the host."""
    blocks = spread(rows).join(large.select("host"), "host", "left_semi").select("id", "url", "host", "html").mapInArrow(_parse, _BLOCKS)
    is_open = F.array_contains("sure", 0)
    hosts = materialize(blocks.where(is_open).select("host").distinct(), "html-open-hosts")
    repeats: dict[str, tuple[np.ndarray, np.ndarray]] = {}
    if hosts.head(1):
        counted = large.join(hosts, "host")
        dealt = blocks.join(_few(counted), "host").withColumn("chunk", F.pmod(F.xxhash64("id", "url"), F.ceil(F.col("pages") / chunk_pages)))
        seen = materialize(dealt.groupBy("host", "chunk").applyInPandas(_windows, "host string, chunk long, window long, n long"), "html-windows")
        totals = seen.groupBy("host", "window").agg(F.sum("n").alias("total")).where(F.col("total") >= MIN_PAGES)
        totals = materialize(totals, "html-totals")
        if totals.count() > INLINE_WINDOWS:
            mine = seen.join(totals, ["host", "window"]).select("host", "chunk", "window", "total")
            cleaned = dealt.groupBy("host", "chunk").cogroup(mine.groupBy("host", "chunk")).applyInPandas(_clean_chunk, _TEXTS)
            others = blocks.join(hosts, "host", "left_anti")
            return cleaned.unionByName(others.mapInPandas(lambda frames: (_clean_by_totals(pdf, {}) for pdf in frames), _TEXTS))
        repeats = _by_host(totals.toPandas())
    return blocks.mapInPandas(lambda frames: (_clean_by_totals(pdf, repeats) for pdf in frames), _TEXTS)


def op4_html_extraction(spark: SparkSession, sf_dir: str) -> DataFrame:
    return extract_pages(spark.read.parquet(f"{sf_dir}/pages.parquet"))
