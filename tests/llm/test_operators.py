"""The ten operators: brute force, round trips, held-out accuracy, and awkward inputs."""

import hashlib
import random
import re

import pytest
from pyspark.sql import functions as F

import __spark_entry__ as contract
from reuse_engine.llm import chat_format, decontaminate, html_extract, jaccard_join, language_id, line_dedup, piece_codec, quality_gam, quality_rules, warc
from reuse_engine import storage
from tests.conftest import SMALL

DOC = "doc_id long, text string, lang string, source string, n_chars long"
EMPTY_TEXTS = [None, "", "   ", "\n\n", "one", "one two three four", " ", "été " * 3]


def docs_of(spark, texts, langs=None, sources=None):
    rows = [(i, t, (langs or ["en"] * len(texts))[i], (sources or [f"s{i % 9}"] * len(texts))[i], len(t or "")) for i, t in enumerate(texts)]
    return spark.createDataFrame(rows, DOC)


@pytest.fixture
def odd(spark):
    """Nulls, empty and very long texts, repeated rows, and columns whose names clash with inner ones."""
    texts = [*EMPTY_TEXTS, "word " * 40_000, "x" * 200_000, "A b c d e f g h i j", "A b c d e f g h i j"]
    d = docs_of(spark, texts)
    d = d.unionByName(d.where("doc_id = 5")).unionByName(spark.createDataFrame([(None, "no id here at all", None, None, None)], DOC))
    for c in ("id", "n", "w", "h", "ls", "site", "body", "token", "component", "score", "x", "y", "n_lines", "votes"):
        d = d.withColumn(c, F.lit("clash"))
    return d


@pytest.fixture
def none(spark):
    return spark.createDataFrame([], DOC)


# --- 1 ---------------------------------------------------------------------------------------


@pytest.mark.parametrize("name", ["op1_benchmark_decontamination", "op2_ngram_jaccard_join", "op5_line_dedup", "op7_chat_formatting", "op9_warc", "quality_base_measures"])
def test_sql_agrees(spark, duck, same_rows, name):
    same_rows(contract.queries()[name](spark, SMALL), duck.sql(contract.oracle_sql()[name]).df())


def test_decontamination_finds_items_in_long_texts(spark, odd, none):
    rng = random.Random(1)
    word = lambda: "".join(rng.choices("abcdefgh", k=5))
    items = [" ".join(word() for _ in range(n)) for n in (8, 40, 90, 300)]
    filler = lambda n: " ".join(word() for _ in range(n))
    texts = [filler(5000) + ", " + it.upper().replace(" ", ". ") + "; " + filler(5000) for it in items] + [filler(3000)]
    half = items[1].split()
    texts.append(filler(100) + " " + " ".join(half[:20]) + " " + filler(100))
    bench = spark.createDataFrame([(i, t) for i, t in enumerate(items)] + [(9, None), (10, "")], "item_id long, text string")
    got = {(r["doc_id"], r["item_id"]) for r in decontaminate.contained_items(docs_of(spark, texts), bench).collect()}
    assert got == {(0, 0), (1, 1), (2, 2), (3, 3)}
    assert decontaminate.contained_items(none, bench).count() == 0 and decontaminate.contained_items(odd, bench.limit(0)).count() == 0
    assert decontaminate.contained_items(odd, spark.createDataFrame([(1, "one two three four"), (2, "B c d e f g")], "item_id long, text string")).count() == 3


def test_decontamination_near_the_threshold(spark):
    """Items of all partitions with a little over and a little under 3/4 of their shingles in a long text."""
    rng = random.Random(12)
    word = lambda: "".join(rng.choices("abcdefghij", k=6))
    items, texts, want = [], [], set()
    for n in (20, 60, 110, 300, 700):
        for share in (0.78, 0.78, 0.72):
            w = [word() for _ in range(n)]
            kept = round(share * (n - 4)) + 4
            texts.append(" ".join([word() for _ in range(400)] + w[:kept] + [word() for _ in range(400)]))
            if 4 * (kept - 4) >= 3 * (n - 4):
                want.add((len(items), len(items)))
            items.append(" ".join(w))
    bench = spark.createDataFrame(list(enumerate(items)), "item_id long, text string")
    got = {(r["doc_id"], r["item_id"]) for r in decontaminate.contained_items(docs_of(spark, texts), bench).collect()}
    assert got == want and 10 <= len(want) < 15
    assert [decontaminate.least_hits(k) for k in (32, 48, 64)] == sorted(decontaminate.least_hits(k) for k in (32, 48, 64))


def test_decontamination_marks_and_short_items(spark, duck):
    passage = "the first thing that we saw when the door had opened"
    texts = [f"He said \u201c{passage.replace(' ', ' \u2014 ')}\u201d.", passage.upper(), "we saw no door", "a b c", "x A-B c y", None, ""]
    bench = spark.createDataFrame([(1, passage), (2, "A b C"), (3, "saw no"), (4, "\u2026"), (5, None)], "item_id long, text string")
    docs = docs_of(spark, texts)
    got = {(r["doc_id"], r["item_id"]) for r in decontaminate.contained_items(docs, bench).collect()}
    assert got == {(0, 1), (1, 1), (2, 3), (3, 2), (4, 2)}
    import duckdb

    c = duckdb.connect()
    c.register("documents", docs.toPandas())
    c.register("benchmark", bench.toPandas())
    assert {(r[0], r[1]) for r in c.sql(decontaminate.OP1_SQL).fetchall()} == got


def test_filtering_stages_on_awkward_rows(spark, odd, none):
    """Repeated ids, null ids and clashing columns: all columns stay, and rows are kept as the docstrings say."""
    bench = spark.createDataFrame([(1, "A b c d e f g h i j")], "item_id long, text string")
    rest = decontaminate.drop_contaminated(odd, bench)
    assert rest.columns == odd.columns and rest.count() == odd.count() - 2 and rest.where("doc_id is null").count() == 1
    kept = jaccard_join.keep_one_per_group(odd)
    assert kept.columns == odd.columns and kept.count() == odd.count() - 1 and kept.where("doc_id is null").count() == 1
    known = language_id.keep_identified(odd)
    assert known.columns == odd.columns and known.where("text is null or trim(text) = ''").count() == 0
    for stage in (lambda d: decontaminate.drop_contaminated(d, bench), jaccard_join.keep_one_per_group, language_id.keep_identified):
        assert stage(none).count() == 0 and stage(none).columns == none.columns


# --- 2 ---------------------------------------------------------------------------------------


def brute_components(texts):
    def shingles(t):
        w = (t or "").encode().lower().split()
        return {tuple(w[i : i + 5]) for i in range(len(w) - 4)} if len(w) >= 5 else ({tuple(w)} if w else set())

    sets = [shingles(t) for t in texts]
    up = list(range(len(texts)))

    def find(x):
        while up[x] != x:
            x = up[x]
        return x

    for i, a in enumerate(sets):
        for j in range(i):
            both = len(a & sets[j])
            if a and sets[j] and 100 * both >= 75 * (len(a) + len(sets[j]) - both):
                x, y = find(i), find(j)
                up[max(x, y)] = min(x, y)
    return {i: (len(sets[i]), find(i)) for i in range(len(texts))}


def family(rng, base, n, edits):
    out = []
    for _ in range(n):
        w = list(base)
        for _ in range(rng.randint(0, edits)):
            w[rng.randrange(len(w))] = f"e{rng.randrange(10**6)}"
        out.append(" ".join(w))
    return out


@pytest.mark.parametrize(("chunk", "small", "seed", "listed"), [(1024, 128, 1, 10**6), (7, 3, 2, 10**6), (5, 2, 3, 0), (7, 3, 4, 300)])
def test_jaccard_join_against_brute_force(spark, monkeypatch, chunk, small, seed, listed):
    """Small limits drive the stars, the chunks, the second probing, salted joins and the buckets of the order."""
    monkeypatch.setattr(jaccard_join, "ORDER_LIMIT", max(listed, 1))
    monkeypatch.setattr(jaccard_join, "COUNTED", 500 if seed == 4 else 4_000_000)
    if not listed:
        monkeypatch.setattr(storage, "BROADCAST_ROWS", 0)
        monkeypatch.setattr(jaccard_join, "BROADCAST_IDS", 0)
    monkeypatch.setattr(jaccard_join, "CHUNK", chunk)
    monkeypatch.setattr(jaccard_join, "SMALL", small)
    monkeypatch.setattr(jaccard_join, "HUBS", 2)
    rng = random.Random(seed)
    words = [f"w{i}" for i in range(300)]
    passage = rng.choices(words, k=30)
    texts = [*EMPTY_TEXTS, "Four words make one", "four WORDS make one"]
    for size, edits in ((25, 3), (60, 4), (120, 9), (200, 12)):
        texts += family(rng, rng.choices(words, k=size), 14, edits)
    texts += [" ".join(rng.choices(words, k=60) + passage) for _ in range(20)]
    texts += [texts[-1]] * 5
    got = {r["doc_id"]: (r["n_shingles"], r["component_id"]) for r in jaccard_join.jaccard_components(docs_of(spark, texts)).collect()}
    assert got == brute_components(texts)


def test_jaccard_join_awkward(spark, odd, none):
    assert jaccard_join.jaccard_components(none).count() == 0
    got = jaccard_join.jaccard_components(odd)
    assert got.count() == odd.count()
    kept = jaccard_join.keep_one_per_group(docs_of(spark, ["a b c d e f", "a b c d e f", None, ""]))
    assert sorted(r["doc_id"] for r in kept.collect()) == [0, 2, 3]


# --- 3 ---------------------------------------------------------------------------------------


def brute_measures(text):
    text = text or ""
    w = re.findall(r"[^\x20\x09-\x0D]+", text)
    win = [tuple(w[i : i + 5]) for i in range(len(w) - 4)]
    seen = {}
    for i, x in enumerate(win):
        seen.setdefault(x, []).append(i)
    covered = {j for at in seen.values() if len(at) > 1 for i in at for j in range(i, i + 5)}
    lines = [x for x in text.split("\n") if re.search(r"[^\x20\x09-\x0D]", x)]
    return len(w), sum(map(len, w)), len(re.findall(r"[#*$%&|<>]", text)), len(lines) - len(set(lines)), len(covered)


def test_quality_measures_against_brute_force(spark, odd, none):
    rng = random.Random(3)
    texts = [*EMPTY_TEXTS] + [" ".join(rng.choices(["a", "b", "#c", "d\n", "\nd", "é&"], k=rng.randint(1, 60))) for _ in range(60)] + ["a b c d e " * 30]
    got = {r["doc_id"]: r for r in quality_rules.judged(docs_of(spark, texts)).collect()}
    for i, t in enumerate(texts):
        r = got[i]
        assert (r["n_words"], r["word_chars"], r["n_symbols"], r["n_dup_lines"], r["n_repeat_words"]) == brute_measures(t)
        assert r["base_failed"] == (r["n_words"] < 10 or 100 * r["n_repeat_words"] > 20 * r["n_words"])
        assert not (r["base_failed"] and r["kept"])
    assert quality_rules.judged(none).count() == 0 and quality_rules.judged(odd).count() == odd.count()


def test_quality_rules_keep_clean_documents(spark):
    d = "/root/testdata/sf0.01"
    got = contract.queries()["op3_quality_rules"](spark, d).join(spark.read.parquet(f"{d}/labels.parquet"), "doc_id").where("not base_failed").toPandas()
    assert got[got.quality == 1].kept.mean() > 0.98 and got[got.quality == 0].kept.mean() < 0.2


def test_estimation_against_brute_force(spark):
    """Expectation-maximisation on vote patterns equals the same rounds on single documents."""
    import numpy as np

    rng = np.random.default_rng(5)
    good = rng.random(600) < 0.85
    right = [(0.98, 0.9), (0.9, 0.6), (0.97, 0.3), (0.8, 0.5)]
    votes = np.stack([np.where(rng.random(600) < np.where(good, g, b), good, ~good).astype(int) for g, b in right], 1)
    votes[rng.random(votes.shape) < 0.2] = -1
    rows = [([None if v < 0 else int(v) for v in row],) for row in votes]
    patterns = spark.createDataFrame(rows, "votes array<tinyint>").groupBy("votes").agg(F.count("*").alias("n"))
    model = quality_rules.estimate(patterns, 4)

    prior, k = quality_rules.PRIOR_VOTES, 4
    pi, rg, rb = quality_rules.START_GOOD, np.full(k, quality_rules.START_RIGHT_GOOD), np.full(k, quality_rules.START_RIGHT_BAD)
    for _ in range(quality_rules.ROUNDS):
        odds = np.log(pi / (1 - pi)) + np.where(votes == 1, np.log(rg / (1 - rb)), np.where(votes == 0, np.log((1 - rg) / rb), 0)).sum(1)
        p = 1 / (1 + np.exp(-odds))
        was = [pi, *rg, *rb]
        yes, no = votes == 1, votes == 0
        pi = (p.sum() + prior * quality_rules.START_GOOD) / (len(p) + prior)
        rg = ((yes.T @ p) + prior * quality_rules.START_RIGHT_GOOD) / ((yes | no).T @ p + prior)
        rb = ((no.T @ (1 - p)) + prior * quality_rules.START_RIGHT_BAD) / ((yes | no).T @ (1 - p) + prior)
        if max(abs(a - b) for a, b in zip(was, [pi, *rg, *rb], strict=True)) < quality_rules.SETTLED:
            break
    assert np.allclose([model.good, *model.right_good, *model.right_bad], [pi, *rg, *rb], atol=1e-6)
    # estimates are those of the votes, not of a bound: rules differ, and the good rule is told from the weak one
    assert model.right_bad[0] > model.right_bad[1] > model.right_bad[2] and model.right_good[3] < 0.9


def test_posterior_is_not_all_must_pass(spark):
    d = "/root/testdata/sf0.01"
    got = contract.queries()["op3_quality_rules"](spark, d).join(spark.read.parquet(f"{d}/labels.parquet"), "doc_id", "left").where("not base_failed").toPandas()
    assert (got.kept & ~got.all_passed).sum() > 30 and not (~got.kept & got.all_passed).any()
    sound = got[got.quality == 1]
    assert sound.kept.mean() > sound.all_passed.mean() + 0.05


# --- 4 ---------------------------------------------------------------------------------------


def page(body, head="<title>t</title>"):
    return f"<!DOCTYPE html><html><head>{head}</head><body>{body}</body></html>"


def test_html_structure(spark):
    body = """<header class="site">Site</header><nav><ul><li>Menu</li></ul></nav><div class="cookie-notice">We use cookies</div>
      <article><h1>A &amp; B</h1><p>First&nbsp;<b>bold</b>
        text.<br>Next <script>var x = "</p>";</script>line</p><aside>Side</aside><p class="ad">Buy</p><ul><li>one</li><li>two</li></ul>
      <form><input value="q"><label>Search</label></form><p>Last &lt;one&gt; &#233;</p><section id="comments"><p>First!</p></section></article>
      <div id="sidebar"><p>More</p></div><footer>&copy; x</footer><!-- <p>no</p> -->"""
    rows = [(1, "http://a.b/1", page(body)), (2, None, None), (3, "", ""), (4, "http://a.b/4", "plain &amp; bare"), (5, "x", "<p>unclosed <b>tag")]
    got = {r["page_id"]: (r["text"], r["n_chars"]) for r in html_extract.extract_pages(spark.createDataFrame(rows, "page_id long, url string, html string")).collect()}
    want = "A & B\n\nFirst bold text. Next line\n\none\n\ntwo\n\nLast <one> é"
    assert got[1] == (want, len(want)) and got[2] == got[3] == ("", 0) and got[4][0] == "plain & bare" and got[5][0] == "unclosed tag"


def test_html_boilerplate_by_host(spark):
    rng = random.Random(5)
    unique = [" ".join(f"u{rng.randrange(10**6)}" for _ in range(60)) for _ in range(40)]
    promo = "join our community of readers and never miss a story again today"
    rows = [(i, f"https://www.h.example/{i}", page(f"<div><p>{u}</p><p>{promo}</p><p>by line {i} {promo} end{i}</p></div>")) for i, u in enumerate(unique)]
    rows.append((99, "https://other.example/", page(f"<div><p>{promo}</p><p>{unique[0]}</p></div>")))
    for chunk in (256, 10):
        got = {r["page_id"]: r["text"] for r in html_extract.extract_pages(spark.createDataFrame(rows, "page_id long, url string, html string"), chunk).collect()}
        assert all(got[i] == f"{u}\n\nby line {i} end{i}" for i, u in enumerate(unique))
        assert got[99] == f"{promo}\n\n{unique[0]}"
    assert html_extract.extract_pages(spark.createDataFrame([], "page_id long, url string, html string")).count() == 0


@pytest.mark.parametrize("inline", [20_000, 0])
def test_html_counts_pages_over_the_host(spark, monkeypatch, inline):
    """The same result for any chunk; what stands in an article stays, however often it is repeated."""
    monkeypatch.setattr(html_extract, "INLINE_WINDOWS", inline)
    rng = random.Random(7)
    words = lambda n: " ".join(f"u{rng.randrange(10**6)}" for _ in range(n))
    promo, notice = "join our community of readers and never miss a story again", "this notice stands in the articles of the host today"
    unique = [words(60) for _ in range(80)]
    rows = [(i, f"https://open.example/{i}", page(f"<div><p>{unique[i]}</p>{f'<p>{promo}</p>' if i % 8 == 0 else ''}</div>")) for i in range(40)]
    rows += [(i, f"https://sure.example/{i}", page(f"<article><p>{unique[i]}</p>{f'<p>{notice}</p>' if i % 2 else ''}</article>")) for i in range(40, 80)]
    want = {i: unique[i] + (f"\n\n{notice}" if i >= 40 and i % 2 else "") for i in range(80)}
    for chunk in (256, 16, 10):
        got = {r["page_id"]: r["text"] for r in html_extract.extract_pages(spark.createDataFrame(rows, "page_id long, url string, html string"), chunk).collect()}
        assert got == want


def test_html_rare_repeats_on_a_large_host(spark):
    """Eight of a thousand pages share a sentence: one chunk or many, it goes."""
    rng = random.Random(17)
    words = lambda n: " ".join(f"u{rng.randrange(10**6)}" for _ in range(n))
    shared, unique = "a sentence that only eight pages of this host have in common", [words(12) for _ in range(1000)]
    rows = [(i, f"https://h.example/{i}", f"<p>{u}</p>{f'<p>{shared}</p>' if i % 125 == 0 else ''}") for i, u in enumerate(unique)]
    for chunk in (2000, 256):
        got = {r["page_id"]: r["text"] for r in html_extract.extract_pages(spark.createDataFrame(rows, "page_id long, url string, html string"), chunk).collect()}
        assert got == dict(enumerate(unique))


@pytest.mark.parametrize(
    ("html", "want"),
    [
        ("<article><p>T</p><div class='share-price'><p>12</p></div><p class='related-work'>r</p><p class='side-effects'>s</p><p id='comment-on-law'>c</p><p>keep</p></article>", "T 12 r s c keep"),
        ("<article><p>T</p><div class='ad'>x</div><div class='cookie-notice'>x</div><ul id=comment-list><li>x</ul><article class='comment'><p>x</p></article><p>keep</p></article>", "T keep"),
        ("<article class=comment>reader</article><p>outside</p>", "outside"),
        ("<article><pre><span class='token comment'># code</span> x</pre></article>", "# code x"),
        ("<p>x<y and z</p>", "x<y and z"),
        ("<p>a <!-- never closed <b>b</b></p>", "a b"),
        ("<!--><p>after</p><!-- <p>no</p> --!><p>too</p>", "after too"),
        ("<p title='a>b'>q</p><a title=it's>z</a>", "q z"),
        ("<p>one <script>if (a < b) '</p>'</script>two</p><style>p{}</style>", "one two"),
        ("<div hidden>h</div><div style='display: none'>n</div><div role=navigation>m</div>ok", "ok"),
        ("<p>a &amp;lt; &#x41;&nbsp;&#10;b", "a &lt; A b"),
    ],
)
def test_html_blocks(html, want):
    assert " ".join(t for t, _ in html_extract.blocks_of(html)) == want


def test_html_scanner_is_linear():
    import time

    for part in ("<p ", '<p a="', "<a \"", "<!--", "<![CDATA[", "<b a=b =\"", "<", "</p ", "<p><b>", "<script "):
        text = part * (1_000_000 // len(part))
        began = time.process_time()
        html_extract.blocks_of(text)
        assert time.process_time() - began < 2, part


def test_html_awkward(spark):
    """Repeated rows, a very long page, null ids, clashing columns, an empty table."""
    long = " ".join(f"w{i}" for i in range(300_000))
    rows = [(1, "http://a/1", "<p>x</p>"), (1, "http://a/1", "<p>x</p>"), (2, "http://a/2", f"<article>{long}</article>"), (None, None, "<p>n</p>"), (3, None, None)]
    pages = spark.createDataFrame(rows, "page_id long, url string, html string")
    for c in ("id", "host", "pages", "texts", "sure", "chunk", "window", "text", "n_chars"):
        pages = pages.withColumn(c, F.lit("clash"))
    for chunk in (256, 1):
        got = sorted((r["page_id"] or 0, r["text"], r["n_chars"]) for r in html_extract.extract_pages(pages, chunk).collect())
        assert got == [(0, "n", 1), (1, "x", 1), (1, "x", 1), (2, long, len(long)), (3, "", 0)]
        assert html_extract.extract_pages(pages.limit(0), chunk).count() == 0


def brute_host(pages):
    """Texts of one host's open pages by exhaustive search: runs of six words on four pages go."""
    split = [[t.split(" ") for t in p] for p in pages]
    holders = {}
    for i, p in enumerate(split):
        for w in p:
            for k in range(len(w) - 5):
                holders.setdefault(tuple(w[k : k + 6]), set()).add(i)
    out = []
    for p in split:
        kept = []
        for w in p:
            gone = {j for k in range(len(w) - 5) if len(holders[tuple(w[k : k + 6])]) >= 4 for j in range(k, k + 6)}
            left = " ".join(x for j, x in enumerate(w) if j not in gone)
            kept += [left] if left else []
        out.append("\n\n".join(kept or [" ".join(w) for w in p]))
    return out


@pytest.mark.parametrize("chunk", [256, 4])
def test_html_against_exhaustive_search(spark, chunk):
    rng = random.Random(11)
    for seed in range(3):
        pages = [[" ".join(rng.choices("abcd"[: 2 + seed], k=rng.randint(1, 14))) for _ in range(rng.randint(1, 4))] for _ in range(25)]
        rows = [(i, f"http://h/{i}", "".join(f"<p>{b}</p>" for b in p)) for i, p in enumerate(pages)]
        got = {r["page_id"]: r["text"] for r in html_extract.extract_pages(spark.createDataFrame(rows, "page_id long, url string, html string"), chunk).collect()}
        assert [got[i] for i in range(25)] == brute_host(pages)


@pytest.mark.parametrize("chunk", [256, 10])
def test_html_short_pages_keep_only_their_own_words(spark, chunk):
    rng = random.Random(8)
    words = lambda n: " ".join(f"u{rng.randrange(10**6)}" for _ in range(n))
    unique, site = [words(40) for _ in range(30)], words(60)
    rows = [(i, f"https://h.example/{i}", page(f"<div><p>{u}</p><p>{site}</p></div>")) for i, u in enumerate(unique)]
    rows += [(30 + i, f"https://h.example/c{i}", page(f"<div><p>{site}</p></div>")) for i in range(5)]
    got = {r["page_id"]: r["text"] for r in html_extract.extract_pages(spark.createDataFrame(rows, "page_id long, url string, html string"), chunk).collect()}
    assert got == {**dict(enumerate(unique)), **{30 + i: site for i in range(5)}}


def test_suffix_array_against_brute_force():
    import numpy as np

    rng = random.Random(6)
    for _ in range(20):
        tokens = [rng.randrange(3) for _ in range(rng.randint(1, 120))]
        order, shared = html_extract.suffix_array(np.array(tokens))
        assert order.tolist() == sorted(range(len(tokens)), key=lambda i: tokens[i:])
        for i in range(1, len(tokens)):
            a, b = tokens[order[i - 1] :], tokens[order[i] :]
            assert shared[i] == next((k for k, (x, y) in enumerate(zip(a, b, strict=False)) if x != y), min(len(a), len(b)))


# --- 5 ---------------------------------------------------------------------------------------


@pytest.mark.parametrize("inline", [20_000, 0])
def test_line_dedup(spark, odd, none, monkeypatch, inline):
    monkeypatch.setattr(line_dedup, "INLINE_LINES", inline)
    foot = "Follow us on every channel"
    long = "this document has its own long line of text number {} which stays"
    texts = [f"{long.format(i)}\n{foot} \n" for i in range(12)] + ["a copied text\nwith lines"] * 12 + [foot, None, ""]
    sources = [f"s{i}" for i in range(12)] * 2 + ["s0", "s1", None]
    got = {r["doc_id"]: r for r in line_dedup.strip_boilerplate(docs_of(spark, texts, sources=sources)).collect()}
    assert all(got[i]["text"] == long.format(i) + "\n" and got[i]["n_removed"] == 1 for i in range(12))
    assert all(got[i]["text"] == texts[i] and got[i]["n_removed"] == 0 for i in range(12, 27))
    assert line_dedup.strip_boilerplate(none).count() == 0 and line_dedup.strip_boilerplate(odd).count() == odd.count()


@pytest.mark.parametrize("inline", [20_000, 0])
def test_lines_proven_elsewhere_go_from_heavy_documents(spark, monkeypatch, inline):
    monkeypatch.setattr(line_dedup, "INLINE_LINES", inline)
    foot, long = "Follow us on every channel", "this document has its own long line of text number {} which stays"
    story = [f"sentence {i} of a story that was copied with small edits" for i in range(9)]
    family = ["\n".join([*story, f"edit {i}"]) for i in range(12)]
    texts = [f"{long.format(i)}\n{foot}" for i in range(12)] + family + [f"{foot}\nshort own", foot, f"{family[0]}\n{foot}"]
    sources = [f"s{i}" for i in range(12)] * 2 + ["s0", "s1", "s2"]
    got = {r["doc_id"]: (r["text"], r["n_removed"]) for r in line_dedup.strip_boilerplate(docs_of(spark, texts, sources=sources)).collect()}
    assert all(got[i] == (long.format(i), 1) for i in range(12)) and all(got[i] == (texts[i], 0) for i in range(12, 24))
    assert got[24] == ("short own", 1) and got[25] == (foot, 0) and got[26] == (family[0], 1)
    monkeypatch.setattr(storage, "BROADCAST_ROWS", 0)
    again = {r["doc_id"]: (r["text"], r["n_removed"]) for r in line_dedup.strip_boilerplate(docs_of(spark, texts, sources=sources)).collect()}
    assert again == got


def test_sketch_decides_like_exact_counts(spark):
    rows = [(line, s) for line, n in ((1, 7), (2, 8), (3, 9), (4, 200), (5, 1)) for s in range(n)]
    texts = [(f"line {a}\nown {a} {s}", f"site{s}") for a, s in rows]
    d = spark.createDataFrame([(i, t, "en", s, 0) for i, (t, s) in enumerate(texts)], DOC)
    found = line_dedup.candidate_lines(d)
    names = {r[0]: i for i in range(1, 6) for r in spark.sql(f"select xxhash64('line {i}')").collect()}
    assert {names[r["line"]] for r in found.collect()} == {2, 3, 4}


# --- 6 ---------------------------------------------------------------------------------------

ODD_STRINGS = ["", " ", "  a  b ", "tab\tnew\nline", "日本語 🙂 x", "<s> hi </s> <0x41>", "a\u0000b", "aaaa" * 30, "   ", "1234 5.6", "é" * 40]


def test_codec_round_trip_and_parity(spark, odd, none):
    got = sorted(piece_codec.encode_documents(docs_of(spark, [*ODD_STRINGS, None])).collect(), key=lambda r: r["doc_id"])
    assert all(r["round_trip"] and r["parity"] for r in got) and got[-1]["n_tokens"] == 0
    codec = piece_codec.PieceCodec(open(piece_codec.MODEL_FILE, "rb").read())
    whole = codec.model.tokenizer()
    for s in ODD_STRINGS:
        ids = codec.encode([s])[0][0]
        assert ids.tolist() == codec.other.encode(s) == whole.encode(s, add_special_tokens=False).ids
        assert codec.decode(ids).decode() == s == whole.decode(ids.tolist())
    assert piece_codec.encode_documents(none).count() == 0
    assert piece_codec.encode_documents(odd).where("not parity").count() == 0


def test_codec_joined_segments_equal_single_ones():
    data = open(piece_codec.MODEL_FILE, "rb").read()
    joined, alone = piece_codec.PieceCodec(data), piece_codec.PieceCodec(data)
    draw, letters = random.Random(5), [*range(33, 127), *range(192, 256), 10, 0x65E5, 0x1D54F]
    words = ["".join(map(chr, draw.choices(letters, k=draw.randint(1, 12)))) for _ in range(3_000)]
    words = list(dict.fromkeys([*words, "", "x" * 200, "<unk>", "</s>", "<0x41>", piece_codec.MARK, f"{piece_codec.MARK}a", *(s for t in ODD_STRINGS for s in joined.segments(t))]))
    joined._learn(words)
    alone._learn_alone(words)
    assert joined.joins and joined.known == alone.known and joined.bad == alone.bad == set()

    class Wrong:
        """A library that differs on the texts that hold one word."""

        def encode(self, texts, num_threads):
            return [[*ids, 7] if "wrong" in t else ids for t, ids in zip(texts, alone.other.encode(texts, num_threads=num_threads), strict=True)]

    differs = piece_codec.PieceCodec(data)
    differs.other = Wrong()
    assert [ok for _, ok in differs.encode(["all is right", "one is wrong", "right again"])] == [True, False, True]
    assert differs.bad == {"wrong"}


def _message(*fields):
    out = b""
    for number, value in fields:
        if isinstance(value, int):
            out += bytes([number << 3 & 127 | (128 if number > 15 else 0), number >> 4] if number > 15 else [number << 3]) + bytes([value])
        elif isinstance(value, float):
            import struct

            out += bytes([number << 3 | 5]) + struct.pack("<f", value)
        else:
            size, enc = len(value), b""
            while True:
                enc += bytes([size & 127 | (128 if size > 127 else 0)])
                size >>= 7
                if not size:
                    break
            out += bytes([number << 3 | 2]) + enc + value
    return out


def test_codec_unigram_model():
    """A model file made here: unigram pieces, byte fallback, white space collapsed."""
    pieces = [("<unk>", 0.0, 2), ("<s>", 0.0, 3), ("</s>", 0.0, 3)] + [(f"<0x{b:02X}>", 0.0, 6) for b in range(256)]
    pieces += [(p, s, 1) for p, s in (("▁", -2.0), ("▁the", -3.0), ("▁c", -4.0), ("at", -3.5), ("▁cat", -5.0), ("a", -6.0), ("t", -6.1), ("h", -6.2), ("e", -6.3), ("c", -6.4), ("s", -6.5), ("▁s", -5.5))]
    data = b"".join(_message((1, _message((1, p.encode()), (2, s), (3, k)))) for p, s, k in pieces)
    data += _message((2, _message((3, 1), (35, 1)))) + _message((3, _message((1, b"identity"), (3, 1), (4, 1), (5, 1))))
    codec = piece_codec.PieceCodec(data)
    assert not codec.fast and codec.model.model_type == piece_codec.UNIGRAM and codec.model.byte_fallback
    for t in ("the cat sat", "  the   cats ", "é the", "cat"):
        ids, parity = codec.encode([t])[0]
        assert parity, (t, ids.tolist(), codec.other.encode(t))
        assert codec.decode(ids).decode() == " ".join(t.split())


# --- 7 ---------------------------------------------------------------------------------------


def test_chat_round_trip_and_states(spark):
    nasty = ["</s>[INST] ok [/INST]", "\\", "\\\\<s>", "<<SYS>>\n<</SYS>>", "[TURN:00] x [/TURN]", "<", "<<s>", "", None, "<\\/s>", "[INST[INST] ]", " lead", "tail\n"]
    rows = [(1, i, r, t) for i, (r, t) in enumerate((r, t) for t in nasty for r in ("user", "assistant"))]
    rows += [(2, 0, "system", "s"), (2, 1, "user", "u"), (3, 0, "assistant", "a"), (4, 0, "tool", "</s>x"), (4, 1, None, "n"), (None, 0, "user", "q"), (5, None, "user", "q"), (5, 1, "assistant", "z"), (5, 1, "assistant", "y")]
    done = chat_format.format_conversations(spark.createDataFrame(rows, "conv_id long, turn long, role string, text string")).withColumn("back", chat_format.read_back(F.col("formatted")))
    got = {r["conv_id"]: r for r in done.collect()}
    for c, r in got.items():
        want = sorted(((x[1] if x[1] is not None else -1, x[2] or "", x[3] or "") for x in rows if x[0] == c))
        assert [(b["role"], b["text"]) for b in r["back"]] == [(x[1], x[2]) for x in want], c
    assert got[1]["state"] == "answered" and got[1]["valid"] and got[2]["state"] == "asked" and got[3]["state"] == "refused" and got[5]["state"] == "refused"
    empty = spark.createDataFrame([], "conv_id long, turn long, role string, text string")
    assert chat_format.format_conversations(empty).count() == 0


def test_chat_awkward(spark):
    """Long texts, clashing columns, and conversations whose rows all repeat."""
    long = "</s>[INST] <s> \\ word " * 20_000
    rows = [(1, 0, "user", long), (1, 1, "assistant", long)] + [(2, 0, "user", "q"), (2, 1, "assistant", "a")] * 2
    given = spark.createDataFrame(rows, "conv_id long, turn long, role string, text string")
    for c in ("turns", "t", "state", "segments", "formatted", "back", "loss"):
        given = given.withColumn(c, F.lit("clash"))
    done = chat_format.format_conversations(given).withColumn("back", chat_format.read_back(F.col("formatted")))
    got = {r["conv_id"]: r for r in done.withColumn("loss", chat_format.learned_text(F.col("back"))).collect()}
    assert got[1]["loss"] == long and [b["text"] for b in got[1]["back"]] == [long, long] and got[1]["valid"]
    assert got[2]["loss"] == "aa" and len(got[2]["back"]) == 4 and got[2]["state"] == "refused"


def test_chat_digests(spark):
    row = contract.queries()["op7_chat_formatting"](spark, SMALL).where("conv_id = -7").first()
    t = "</s>[INST] ok [/INST]"
    assert row["n_turns"] == 2 and row["loss_chars"] == len(t) and row["loss_sha256"] == hashlib.sha256(t.encode()).hexdigest()
    assert row["turns_sha256"] == hashlib.sha256(f"user\n{t}\nassistant\n{t}\n".encode()).hexdigest()


# --- 8 ---------------------------------------------------------------------------------------


def brute_bits(model_counts, order, alphabet, body, symbol):
    """Code length of a text straight from the counts, symbol by symbol."""
    import math

    s = [symbol[b] for b in b"   "[:order] + body.lower()]
    bits = 0.0
    for i in range(order, len(s)):
        p, k = 1.0, order
        while True:
            ctx = tuple(s[i - k : i])
            seen = model_counts[k].get(ctx)
            if seen:
                total, distinct = sum(seen.values()), len(seen)
                if s[i] in seen:
                    p *= seen[s[i]] / (total + distinct)
                    break
                p *= distinct / (total + distinct)
            if k == 0:
                p /= alphabet
                break
            k -= 1
        bits -= math.log2(p)
    return bits


def test_code_lengths_against_brute_force():
    import numpy as np

    texts = [b"the cat sat on the mat and the rat", b"a different text, 42!"]
    u, c = np.unique(np.concatenate([language_id._grams(t) for t in texts]), return_counts=True)
    other = np.unique(language_id._grams(bytes(range(256)) * 3), return_counts=True)
    model = language_id.FrozenModel(["x", "y"], [u, other[0]], [c, other[1]])
    counts = [{} for _ in range(4)]
    for t in texts:
        s = list(b"   " + t.lower())
        for i in range(3, len(s)):
            for k in range(4):
                d = counts[k].setdefault(tuple(s[i - k : i]), {})
                d[s[i]] = d.get(s[i], 0) + 1
    for t in (b"the mat", b"Zebra 7 \xc3\xa9", b"c", b"the cat \xff\xfe the cat " * 40):
        assert abs(model.code_lengths(t)[0] - brute_bits(counts, 3, 256, t, range(256))) < 1e-4 * (len(t) + 1)
        assert np.allclose(model.all_lengths([b"x", t, b"", t])[[1, 3]], model.code_lengths(t))


def test_many_languages_and_scripts(spark):
    """Nine languages of one script each: the order does not fall, and no byte stands for another."""
    starts = [0x3B1, 0x430, 0x561, 0x5D0, 0x627, 0x905, 0x3042, 0x10D0, 0x61]
    rng = random.Random(4)
    text = lambda s: " ".join("".join(chr(s + rng.randrange(20)) for _ in range(rng.randint(2, 8))) for _ in range(30))
    langs = [f"l{i}" for i in range(9)]
    learned = docs_of(spark, [text(s) for s in starts for _ in range(6)], [x for x in langs for _ in range(6)])
    asked = docs_of(spark, [text(s) for s in starts], langs)
    got = {r["doc_id"]: r["lang_pred"] for r in language_id.identify(asked, language_id.learn(learned)).collect()}
    assert [got[i] for i in range(9)] == langs


def test_language_held_out_accuracy(spark, odd, none):
    d = "/root/testdata/sf0.01"
    got = contract.queries()["op8_language_id"](spark, d).join(spark.read.parquet(f"{d}/documents.parquet").select("doc_id", "lang"), "doc_id").where("held_out").toPandas()
    assert (got.lang == got.lang_pred).mean() > 0.98 and got.score.between(0, 1).all()
    counts = language_id.learn(docs_of(spark, ["hello there friend"] * 4, ["en"] * 4))
    out = {r["doc_id"]: r for r in language_id.identify(odd, counts).collect()}
    assert [out[i]["lang_pred"] for i in (0, 1, 2, 3, 6)] == ["und"] * 5 and out[4]["lang_pred"] == "en"
    assert language_id.identify(none, language_id.learn(none)).count() == 0
    assert language_id.identify(odd, language_id.learn(none)).where("lang_pred <> 'und'").count() == 0


# --- 9 ---------------------------------------------------------------------------------------


@pytest.mark.parametrize("limit", [1_000_000, 0])
def test_warc_round_trip(spark, tmp_path, monkeypatch, limit):
    monkeypatch.setattr(storage, "BROADCAST_ROWS", limit)
    long = "<p>long payload</p>" * 200_000
    rows = [(1, "http://a/\r\nX: y", "<p>same</p>"), (2, None, "<p>same</p>"), (3, "u%0A", None), (4, "", ""), (5, "é", "<p>ü\u0000</p>" * 50), (5, "é", "<p>ü\u0000</p>" * 50), (None, "n", "<p>same</p>")]
    rows += [(100 + i, f"http://h/{i}", f"<html><body>page {i} with shared words</body></html>") for i in range(200)]
    rows += [(400, "http://l/1", long), (401, "http://l/2", long), (402, "http://l/3", long + "x"), (500, "a", "twice the id"), (500, "b", "other payload")]
    pages = spark.createDataFrame(rows, "page_id long, url string, html string")
    for c in ("digest", "response", "row", "first_id", "target", "record_id", "data", "name"):
        pages = pages.withColumn(c, F.lit("clash"))
    archives = warc.write_archives(pages)
    for got in (warc.read_archives(archives), _through_files(spark, archives, tmp_path)):
        found = got.collect()
        assert len(found) == len(rows) and all(r["intact"] for r in found)
        by = {(r["page_id"], r["url"]): r for r in found}
        for i, url, html in rows:
            body = (html or "").encode()
            assert by[i, url]["payload_bytes"] == len(body) and by[i, url]["payload_digest"] == warc.base32_sha1(body)
        one = {r["page_id"]: r for r in found}
        assert (one[1]["record_type"], one[1]["refers_to"]) == ("revisit", 2) and one[2]["record_type"] == "response" and one[None]["record_type"] == "response"
        assert (one[3]["record_type"], one[3]["refers_to"]) == ("revisit", 4) and one[5]["record_type"] == "response"
        assert (one[400]["record_type"], one[400]["refers_to"]) == ("revisit", 401) and one[402]["record_type"] == "response"
        assert len({r["record_id"] for r in found}) == len(set(rows))
    assert warc.read_archives(warc.write_archives(pages.limit(0))).count() == 0


def test_warc_damage_is_seen(spark):
    """A payload that is not the stated one, and revisits of it or of nothing, are not intact; a cut archive is refused."""
    good, bad = warc.base32_sha1(b"good"), warc.base32_sha1(b"bad")
    records = [warc.record(1, "u", b"good", None, good), warc.record(2, "u", b"good", None, bad), warc.record(3, "u", b"good", warc.record_urn(1, "u", good), good),
               warc.record(4, "u", b"bad", warc.record_urn(2, "u", bad), bad), warc.record(5, "u", b"good", "<urn:uuid:none>", good)]
    archive = warc.pack(records)
    got = {r["page_id"]: r for r in warc.read_archives(spark.createDataFrame([(bytearray(archive),)], "data binary")).collect()}
    assert [got[i]["intact"] for i in range(1, 6)] == [True, False, True, False, False]
    assert got[2]["payload_digest"] == good and got[3]["payload_bytes"] == 4 and got[5]["payload_bytes"] is None
    with pytest.raises(Exception, match="cut off"):
        list(warc.unpack(archive[:-3]))


def test_warc_reads_in_linear_time():
    import time

    def took(n):
        archive = warc.pack([warc.record(i, f"http://h/{i}", (f"<p>{i}</p>" * 150).encode(), None, "D") for i in range(n)])
        began = time.process_time()
        assert sum(1 for _ in warc.unpack(archive)) == n
        return time.process_time() - began

    took(2000)
    assert took(40_000) < 40 * max(took(4000), 0.004)


def _through_files(spark, archives, tmp_path):
    assert warc.export_archives(archives, f"file://{tmp_path}/warc").count() == archives.count()
    return warc.read_archive_files(spark, f"{tmp_path}/warc")


def test_warc_dictionary_and_single_frames():
    import zstandard

    records = [warc.record(i, "u", f"<html>{i} common words in every page of this site</html>".encode() * 3, None, "D") for i in range(300)]
    data = warc.pack(records)
    assert list(warc.unpack(data)) == records
    plain = sum(len(zstandard.ZstdCompressor(level=3).compress(r)) for r in records)
    assert len(data) < plain
    magic, size = int.from_bytes(data[:4], "little"), int.from_bytes(data[4:8], "little")
    assert magic == warc.DICTIONARY_MAGIC and size > 0 and list(warc.unpack(warc.pack([b"x"]))) == [b"x"]


# --- 10 --------------------------------------------------------------------------------------


def test_quality_model_held_out(spark, odd, none):
    d = "/root/testdata/sf0.01"
    got = contract.queries()["op10_quality_classifier"](spark, d).join(spark.read.parquet(f"{d}/labels.parquet"), "doc_id").where("held_out").toPandas()
    assert (got.predicted == got.quality).mean() > 0.95 and got.score.between(0, 1).all()
    labels = spark.createDataFrame([(i, i % 2, 0) for i in range(12)], "doc_id long, quality int, toxic int")
    for lab in (labels, labels.limit(0), labels.withColumn("quality", F.lit(1)), labels.withColumn("quality", F.lit(None).cast("int"))):
        assert quality_gam.score_quality(odd, quality_gam.fit_quality(odd, lab)).count() == odd.count()
    assert quality_gam.score_quality(none, quality_gam.fit_quality(none, labels)).count() == 0


def test_scores_are_sums_of_table_entries():
    """Vectorised scoring against a loop over rows, features and pairs."""
    import bisect
    import math

    import numpy as np

    rng = np.random.default_rng(8)
    x = rng.random((400, 4)).round(2)
    model = quality_gam.AdditiveModel().fit(x[:300], ((x[:300, 0] > 0.4) & (x[:300, 2] < 0.7)).astype(float))
    for row, score in zip(x[300:], model.score(x[300:]), strict=True):
        place = [bisect.bisect_right(cuts.tolist(), v) for cuts, v in zip(model.cuts, row, strict=True)]
        z = model.start + sum(t[i] for t, i in zip(model.tables, place, strict=True)) + sum(t[place[a], place[b]] for (a, b), t in zip(model.pairs, model.pair_tables, strict=True))
        assert abs(score - 1 / (1 + math.exp(-z))) < 1e-9


def test_quality_features_against_plain_counts():
    for text in ("Good words, and good words.\nGood words!", "## $$ | A1 b", "", None, "é" * 3):
        got = dict(zip(quality_gam.FEATURES, quality_gam.features(None if text is None else text.encode()), strict=True))
        body = (text or "").encode()
        for name, chars in quality_gam._DELETE.items():
            assert got[name] == sum(b in chars for b in body) / max(len(body), 1)


def test_repeated_labels_of_an_id(spark):
    """The largest label of an id counts, so the order of repeated label rows does not matter."""
    docs = docs_of(spark, [("good words " if i % 2 else "## $$ ") * 20 for i in range(60)])
    once = spark.createDataFrame([(i, i % 2, 0) for i in range(60)], "doc_id long, quality int, toxic int")
    twice = once.unionByName(once.where("quality = 1").withColumn("quality", F.lit(0))).unionByName(once)
    scores = [sorted((r["doc_id"], r["score"]) for r in quality_gam.score_quality(docs, quality_gam.fit_quality(docs, lab)).collect()) for lab in (once, twice)]
    assert scores[0] == scores[1] and all((s >= 0.5) == (i % 2 == 1) for i, s in scores[0])


def test_additive_model_learns_an_interaction():
    import numpy as np

    rng = np.random.default_rng(2)
    x = rng.random((4000, 3))
    y = ((x[:, 0] > 0.5) ^ (x[:, 1] > 0.5)).astype(float)
    model = quality_gam.AdditiveModel().fit(x[:3000], y[:3000])
    assert (0, 1) in model.pairs and ((model.score(x[3000:]) >= 0.5) == y[3000:]).mean() > 0.95
    assert np.allclose(quality_gam.AdditiveModel().fit(np.zeros((0, 3)), np.zeros(0)).score(x[:2]), 0.5)


# --- pipeline --------------------------------------------------------------------------------


def test_pipeline_against_sql_and_the_library(spark):
    """Every stage stated anew: frozen models by plain loops, SQL on what the stage before left, and the SentencePiece library."""
    import duckdb
    import sentencepiece

    import corpus_pipeline
    from reuse_engine.llm import decontaminate

    given = spark.read.parquet(f"{SMALL}/documents.parquet")
    counts = language_id.learn(given)
    model = language_id.FrozenModel(counts["langs"], counts["grams"], counts["counts"])
    docs = given.toPandas()
    found = [model.predict(None if t is None else t.encode()) for t in docs.text]
    docs = docs[[lang != "und" and score >= 0.5 for lang, score in found]]
    c = duckdb.connect()
    c.execute(f"create view benchmark as select * from read_parquet('{SMALL}/benchmark.parquet')")

    def state(sql):
        c.register("documents", docs)
        return c.sql(sql).df()

    docs = docs.drop(columns="text").merge(state(line_dedup.OP5_SQL)[["doc_id", "text"]], on="doc_id")
    groups = state(jaccard_join.OP2_SQL)
    docs = docs[docs.doc_id.isin(groups[groups.doc_id == groups.component_id].doc_id)]
    docs = docs[~docs.doc_id.isin(state(decontaminate.OP1_SQL).doc_id)]
    library = sentencepiece.SentencePieceProcessor(model_file=piece_codec.MODEL_FILE)
    want = {r.doc_id: library.encode(r.text) for r in docs.itertuples()}
    assert {r["doc_id"]: r["tokens"] for r in corpus_pipeline.run(spark, SMALL).collect()} == want


def test_pipeline(spark):
    import corpus_pipeline

    out = corpus_pipeline.run(spark, SMALL).toPandas()
    docs = spark.read.parquet(f"{SMALL}/documents.parquet").toPandas()
    assert out.doc_id.is_unique and set(out.doc_id) <= set(docs.doc_id) and out.round_trip.all() and out.parity.all()
    assert 0.7 * len(docs) < len(out) < len(docs)
    given = spark.read.parquet(f"{SMALL}/documents.parquet")
    for _, stage in corpus_pipeline.STAGES[:-1]:
        assert stage(spark, given, SMALL).columns == given.columns
        assert stage(spark, given.limit(0), SMALL).count() == 0
