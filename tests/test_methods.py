"""Golden values, invariants and plan shapes."""

import numpy as np
import pytest
from hypothesis import given, settings
from hypothesis import strategies as st
from pyspark.sql import functions as F

from reuse_engine.functions.dialects import DIALECTS
from reuse_engine.functions.symbols import fingerprint, score_bp
from reuse_engine.graph import connected_components
from reuse_engine.operators import assignment, bundles, findings, homogeneity, pairing, preprocess
from reuse_engine.plans.methods import fingers_of
from reuse_engine.storage import table
from tests.conftest import SMALL

R = {
    "R1": "60806040526004361057600080fd5b60016002015600", "R2": "60ff60aa52600b361057600180fd5b60036004015600", "R3": "60806040526004361057600080fd5b60016002035600",
    "R4": "605760f300", "R5": "6001617f", "R6": "5b6001",
}


def _vm(spark, rows):
    vm = DIALECTS["vmhex"]
    df = spark.createDataFrame(list(rows.items()), "name string, payload string")
    df = df.withColumn("runtime", vm.strip_trailer(vm.strip_prefix(F.col("payload")))).withColumn("tok", vm.tokens(F.col("runtime"), True)).withColumn("pieces", vm.pieces(F.col("tok")))
    df = df.withColumn("fp", fingerprint(F.col("pieces"))).withColumn("fp4", fingerprint(F.col("pieces"), digest_chars=4)).withColumn("h", F.md5(F.replace("tok", F.lit(" "), F.lit(""))))
    return {r["name"]: r for r in df.collect()}


def test_golden_programs(spark):
    got = _vm(spark, R)
    assert [got[k]["fp"] for k in R] == ["DLs8", "DLs8", "DLs8", "D", "d", "C"]
    assert [got[k]["fp4"] for k in R] == ["r4Ix", "r4Ix", "r4Cx", "P", "1", "R"]
    assert got["R1"]["pieces"] == ["60605260361057", "6080fd", "5b60600156", "00"]
    assert got["R1"]["h"] == got["R2"]["h"] == "f266c0ca001d8b4d2ffe110fa7970f49" and got["R3"]["h"] == "c2506a40abb09e7f352bd9e64e9eda4d"


def test_regions(spark):
    trailer = lambda c: "a165627a7a72305820" + c * 64 + "0029"
    rows = {"a": "60015b6000f300" + R["R1"] + trailer("1"), "b": "60015b6000f300" + R["R1"] + trailer("2"), "odd": "a6000f3001", "none": R["R1"], "two": "60015b6000f3006000f300" + R["R1"]}
    got = _vm(spark, rows)
    assert got["a"]["runtime"] == got["b"]["runtime"] == R["R1"]
    assert got["odd"]["runtime"] == "a6000f3001" and got["none"]["runtime"] == R["R1"]
    assert got["two"]["runtime"] == "6000f300" + R["R1"]


@pytest.mark.parametrize(("dist", "longest", "bp"), [(0, 10, 10000), (3, 25, 8800), (3, 10, 7000), (4, 13, 6923), (10, 10, 0)])
def test_scores(spark, dist, longest, bp):
    assert spark.range(1).select(score_bp(F.lit(dist).cast("bigint"), F.lit(longest).cast("bigint"))).first()[0] == bp


def _fps(spark, strings):
    rows = [("c", "o", f"u{i:03d}", s, len(s), len(s) * 3) for i, s in enumerate(strings)]
    df = spark.createDataFrame(rows, "corpus string, origin string, unit_id string, fp string, fp_len int, n_ops long")
    for c in ("n_pieces", "n_distinct_ops", "n_terminators", "n_operand_bytes", "n_bytes"):
        df = df.withColumn(c, F.col("n_ops"))
    return df


@pytest.mark.parametrize("threshold", [40, 70, 90])
def test_candidate_plans_agree(spark, threshold):
    rng = np.random.default_rng(7)
    base = ["".join(rng.choice(list("abcd"), rng.integers(1, 14))) for _ in range(50)]
    fps = _fps(spark, base + [b[:-1] + "z" for b in base[:20]] + ["", ""])
    key = lambda df: {(r["a"], r["b"], r["score_bp"]) for r in df.collect()}
    every = key(pairing.similar_pairs(fps, threshold, how="theta", prune=None))
    assert key(pairing.similar_pairs(fps, threshold, how="qgram", prune=None)) == every
    assert key(pairing.similar_pairs(fps, threshold, how="band", prune="fp_len")) == every
    assert key(pairing.similar_pairs(fps, threshold, how="band", prune="bag")) == every
    assert key(pairing.similar_pairs(fps, threshold, how="minhash", prune=None)) <= every
    assert key(pairing.similar_pairs(fps, threshold, how="band", prune="attrs")) == key(pairing.similar_pairs(fps, threshold, how="theta", prune="attrs"))
    assert key(pairing.similar_pairs(fps, threshold, how="band")) == key(pairing.similar_pairs(fps, threshold, how="theta", prune="length"))


def test_length_rule_boundary(spark):
    keep = lambda a, b: spark.createDataFrame([(a, b)], "n_ops_a long, n_ops_b long").where(pairing.prune_condition("length")).count() == 1
    assert keep(70, 100) and not keep(69, 100) and keep(7, 10)


def test_default_plan_has_no_nested_loop(spark):
    plan = pairing.similar_pairs(fingers_of(spark, SMALL, ["documents"]))._jdf.queryExecution().executedPlan().toString()
    assert "NestedLoop" not in plan and "Cartesian" not in plan


def test_pushdown_and_pruning(spark):
    plan = table(spark, SMALL, "events").where("event_type = 'purchase'").select("event_id")._jdf.queryExecution().executedPlan().toString()
    assert "EqualTo(event_type,purchase)" in plan and "props" not in plan.split("ReadSchema")[1]


@settings(max_examples=8, deadline=None)
@given(st.lists(st.tuples(st.integers(0, 25), st.integers(0, 25)), max_size=30))
def test_components_against_union_find(spark, edges):
    up = {}

    def find(x):
        up.setdefault(x, x)
        while up[x] != x:
            x = up[x]
        return x

    for a, b in edges:
        if a != b:
            i, j = find(a), find(b)
            up[max(i, j)] = min(i, j)
    df = spark.createDataFrame(edges, "a long, b long") if edges else spark.createDataFrame([], "a long, b long")
    assert {r["vertex"]: r["component"] for r in connected_components(df).collect()} == {x: find(x) for x in up}


@settings(max_examples=200, deadline=None)
@given(st.integers(1, 5), st.integers(1, 5), st.data())
def test_assignment_is_optimal(n, m, data):
    w = np.array(data.draw(st.lists(st.lists(st.integers(0, 100), min_size=m, max_size=m), min_size=n, max_size=n)))
    total, pairs = assignment.max_weight(w)
    assert total == assignment.brute_force(w) >= assignment.greedy(w)[0]
    assert len({a for a, _ in pairs}) == len(pairs) == len({b for _, b in pairs}) and total == sum(w[a, b] for a, b in pairs)


def test_assignment_fixture():
    w = np.array([[90, 80], [85, 10]])
    assert assignment.max_weight(w)[0] == 165 and assignment.greedy(w)[0] == 100


def test_directions(spark):
    m = spark.createDataFrame([("x", "y", 2, 3, 16500)], "ua string, ub string, n_a long, n_b long, total_bp long")
    r = bundles.bundle_similarity(m).first()
    assert (r["sim_ab_bp"], r["sim_ba_bp"], r["sim_bp"]) == (8250, 5500, 8250)


def test_behaviour_classes(spark):
    cases = [({}, {}, "neither"), ({"x": 2}, {"x": 2}, "both_same"), ({"x": 1}, {}, "one"), ({"x": 2, "y": 1}, {"x": 1}, "overlap"), ({"x": 1}, {"y": 1}, "disjoint"), ({"x": 1}, {"x": 2}, "overlap")]
    rows, pairs = [], []
    for i, (a, b, _) in enumerate(cases):
        rows += [(f"a{i}", k, n) for k, n in a.items()] + [(f"b{i}", k, n) for k, n in b.items()]
        pairs.append((f"a{i}", f"b{i}"))
    found = spark.createDataFrame(rows, "unit_id string, ftype string, n long")
    units = spark.createDataFrame([(x, "me", 1) for p in pairs for x in p], "unit_id string, creator string, first_seen_us long")
    got = {r["a"]: r["cls"] for r in findings.classified_pairs(spark.createDataFrame(pairs, "a string, b string"), units, found).collect()}
    assert [got[f"a{i}"] for i in range(len(cases))] == [c for _, _, c in cases]


def test_top_share_by_both_weights(spark):
    sizes = spark.createDataFrame([("a", 5, 5), ("b", 2, 200), ("c", 1, 1)], "cluster_id string, n_units long, n_artifacts long")
    assert homogeneity.top_share(sizes, 20, "n_units").first()["share_bp"] == 6250
    assert homogeneity.top_share(sizes, 20, "n_artifacts").first()["share_bp"] == 10000 * 200 // 206


def test_units_count_all_artifacts(spark):
    from reuse_engine.plans.methods import norm_of

    norm = norm_of(spark, SMALL, ["scripts", "documents"])
    units = preprocess.units(norm)
    assert units.agg(F.sum("n_dup")).first()[0] == norm.count()
    assert units.where("n_runtime > n_dup").count() == 0


def test_impact_ratio(spark):
    cl = spark.createDataFrame([("o", "k"), ("c", "k")], "bundle_id string, cluster_id string")
    b = spark.createDataFrame([("o", "x", 1, 187950872), ("c", "y", 2, 1778146)], "bundle_id string, owner string, deployed_us long, volume_milli long")
    assert bundles.volume_impact(cl, b).first()["ratio_bp"] == 94  # 0.94 %, not the printed 9.38 %


# --- hashes and cutting against plain loops ---------------------------------------------------


def _fnv(text):
    h = 2166136261
    for b in text.encode():
        h = ((h ^ b) * 16777619) & 0xFFFFFFFF
    return h


def test_piece_hashes_against_other_libraries(spark):
    import zlib

    import pandas as pd
    import xxhash

    from reuse_engine.functions.symbols import piece_hash
    from reuse_engine.plans.surround import fnv1a32

    pieces = ["", "a", "6080604052", "été ü", "x" * 300]
    rows = spark.createDataFrame([(p,) for p in pieces], "p string").select("p", *[piece_hash(F.col("p"), a).alias(a) for a in ("crc32", "xxhash64", "fnv1a32")]).collect()
    for r in rows:
        t = r["p"]
        assert (r["crc32"], r["xxhash64"], r["fnv1a32"]) == (zlib.crc32(t.encode()), xxhash.xxh64_intdigest(t.encode(), seed=42) % (1 << 32), _fnv(t))
    got = fnv1a32(pd.Series([*pieces, None]))
    assert got[:5].tolist() == [_fnv(p) for p in pieces] and got.isna().tolist() == [False] * 5 + [True]


def test_rolling_cut_against_a_loop(spark):
    import zlib

    from reuse_engine.operators import fingerprints

    rng = np.random.default_rng(3)
    rows = [(f"u{i}", " ".join(rng.choice(["60", "52", "56", "5b", "f3"], rng.integers(0, 60)))) for i in range(30)]
    got = fingerprints.pieces(spark.createDataFrame(rows, "unit_id string, tok string"), "vmhex", "rolling", window=7, modulus=4).collect()
    for r in got:
        tokens, want, piece = r["tok"].split(" ") if r["tok"] else [], [], []
        for i, t in enumerate(tokens):
            piece.append(t)
            if sum(zlib.crc32(x.encode()) for x in tokens[max(0, i - 6) : i + 1]) % 4 == 3:
                want.append(" ".join(piece))
                piece = []
        assert r["pieces"] == want + ([" ".join(piece)] if piece else [])


# --- passages, templates, lossy pairs ----------------------------------------------------------


def test_passages_of_any_length(spark):
    texts = {"a": "one two three four five six", "b": "xone two three four fivex", "c": "the one", "d": "", "e": "two  three four five   six", "f": "short"}
    passages = ["one two three four five", "two three four", "the one", "e o", "ort", "", None, "two  three four five   six", "four"]
    rows = spark.createDataFrame(list(texts.items()), "unit_id string, payload string")
    got = {(r[0], r[1]) for r in findings.passages_held(rows, spark.createDataFrame([(p,) for p in passages], "text string")).collect()}
    assert got == {(u, p) for u, t in texts.items() for p in passages if p and p in t}


def test_one_template_in_many_bundles(spark):
    """Bundles that share a template only are no clones, are counted as emptied, and their number does not square."""

    def run(n):
        mem = [(f"b{i}", "tpl") for i in range(n)] + [(f"b{i}", f"own{i}") for i in range(0, n, 2)] + [("x", "core1"), ("x", "core2"), ("y", "core1"), ("y", "core3")]
        members = spark.createDataFrame(mem, "bundle_id string, unit_id string")
        owners = spark.createDataFrame([(b, f"o{b}", 1, 1) for b in {m[0] for m in mem}], "bundle_id string, owner string, deployed_us long, volume_milli long")
        pairs = spark.createDataFrame([("core2", "core3", 9000), ("own0", "tpl", 8000)], "a string, b string, score_bp long")
        cl = spark.createDataFrame([("core2", "core2"), ("core3", "core2")], "unit_id string, cluster_id string")
        catalogue = homogeneity.template_catalogue(spark.createDataFrame([("core2", "core2", 2)], "cluster_id string, template_unit string, n_members long"), members)
        left = homogeneity.drop_templates(members, homogeneity.template_units(catalogue, cl, pairs))
        out = homogeneity.elimination(members, left)
        weights = bundles.bipartite(left, owners, pairs)
        clones = {(r["ua"], r["ub"]) for r in bundles.bundle_clones(left, owners, pairs).collect()}
        return out.where("emptied").count(), weights.count(), clones

    small, large = run(24), run(120)
    assert small == (12 + 1, 2, {("x", "y")}) and large == (60 + 1, 2, {("x", "y")})


@pytest.mark.parametrize("corpus", ["documents", "pages"])
@pytest.mark.parametrize("d", ["/root/testdata/sf0.01", "/root/testdata/sf0.1"])
def test_lossy_pairs_lose_little(spark, corpus, d):
    from reuse_engine.operators import calibration

    fps = fingers_of(spark, d, [corpus])
    loss = calibration.pruning_loss(pairing.similar_pairs(fps), pairing.similar_pairs(fps, how="minhash")).first()
    assert loss["n_similar"] > 10 and loss["loss_bp"] <= 1000


def test_compared_counts_against_pairs(spark):
    rng = np.random.default_rng(9)
    fps = _fps(spark, ["a" * int(n) for n in rng.integers(1, 40, 120)])
    assert pairing.compared_counts(fps).first()["n_compared"] == pairing.candidate_pairs(fps, "theta", "length").count()


def test_component_variants_agree(spark):
    from reuse_engine.graph import driver_components, label_min

    rng = np.random.default_rng(2)
    edges = spark.createDataFrame([(int(a), int(b)) for a, b in rng.integers(0, 60, (45, 2))], "a long, b long")
    rows = [sorted(map(tuple, f(edges).collect())) for f in (connected_components, label_min, driver_components)]
    assert rows[0] == rows[1] == rows[2]


def test_updates_of_several_batches(spark):
    """Keys that only an early batch touched keep their rows."""
    from reuse_engine.streaming import streams

    arts = spark.createDataFrame([(f"a{i}", "c", 100 - i, f"k{i % 7}") for i in range(40)], "artifact_id string, corpus string, deployed_us long, token_hash string")
    stream = streams.artifact_stream(arts, "test", 8).select(F.lit("o").alias("origin"), "token_hash", "artifact_id", F.col("deployed_us").alias("us"))
    labels = spark.createDataFrame([("o", f"k{i}", f"k{i}") for i in range(7)], "origin string, token_hash string, cluster_id string")
    got = {r["cluster_id"]: r["artifact_id"] for r in streams.run_now(streams.cluster_originals(stream, labels), "test", "update", ("cluster_id",)).collect()}
    assert got == {f"k{k}": f"a{max(i for i in range(40) if i % 7 == k)}" for k in range(7)}


def test_declared_schemas(spark):
    from reuse_engine import schemas
    from reuse_engine.plans import methods, workloads
    from reuse_engine.sources.artifacts import CORPORA, artifacts

    for c in CORPORA:
        schemas.conform(artifacts(spark, SMALL, c), "artifacts")
    schemas.conform(methods.norm_of(spark, SMALL, ["vm", "pages"]), "normalized")
    schemas.conform(methods.units_of(spark, SMALL, ["documents"]), "units")
    fps, pairs, cl = workloads.cluster_parts(spark, SMALL, "documents")
    mem, bun = workloads.bundle_parts(spark, SMALL, "documents")
    made = {"fingerprints": fps, "pairs": pairs, "clusters": cl, "findings": workloads.finding_parts(spark, SMALL)[1], "members": mem, "bundles": bun, "clones": workloads.clones_of(spark, SMALL)[0]}
    for name, df in made.items():
        schemas.conform(df, name)
    with pytest.raises(TypeError, match="n_dup"):
        schemas.conform(fps.drop("n_dup"), "fingerprints")


def test_shared_tables(spark, tmp_path):
    """One write for the same sources, another for changed ones; a table that was removed is written again."""
    from reuse_engine import storage

    calls = []

    def build():
        calls.append(1)
        return spark.range(3)

    (tmp_path / "one").write_text("x")
    for _ in range(2):
        storage.shared_table(spark, str(tmp_path), "test", (), build)
    (tmp_path / "two").write_text("y")
    made = storage.shared_table(spark, str(tmp_path), "test", (), build)
    assert len(calls) == 2 and made.count() == 3
    first = storage.materialize(spark.range(5), "test")
    storage.discard(first)
    with pytest.raises(Exception):  # noqa: B017
        first.count()


def test_planted_bundles_are_found_by_their_size(spark):
    """A copy that exchanges one of n units is a clone at 70 from four units on, and nothing else is."""
    from reuse_engine.plans import workloads

    rows = workloads._c16x(spark, SMALL).collect()
    assert rows and all(r["n_found"] == (r["n_planted"] if r["n_units"] >= 4 else 0) for r in rows)
    pairs = workloads.planted_clones(spark, SMALL)[0].collect()
    assert pairs and all(p["ua"] == f"copy/{p['ub']}" and p["sim_bp"] == 7500 for p in pairs)


def test_chunk_meetings_against_all_pairs():
    """Random, edited, repeating and long texts: no pair that reaches a threshold is missed, and few others are kept."""
    import random

    from reuse_engine.operators.chunks import meetings

    draw = random.Random(7)
    texts = ["".join(draw.choice("ABCDEFGH") for _ in range(draw.randint(1, 30))) for _ in range(60)]
    for t in list(texts):
        chars = list(t)
        for _ in range(draw.randint(1, 4)):
            at = draw.randrange(len(chars) + 1)
            chars[at : at + draw.randint(0, 1)] = [draw.choice("ABCDEFGH一")] * draw.randint(0, 1)
        texts.append("".join(chars) or "A")
    texts += ["A" * 300, "A" * 260 + "B" * 20, "AB" * 150, "C" + "A" * 299]

    def dist(x, y):
        row = list(range(len(y) + 1))
        for i, c in enumerate(x, 1):
            last, row[0] = row[0], i
            for j, e in enumerate(y, 1):
                last, row[j] = row[j], min(row[j] + 1, row[j - 1] + 1, last + (c != e))
        return row[-1]

    far = [[dist(x, y) for y in texts] for x in texts]
    for t in (40, 70, 90, 100):
        got = set(zip(*(i.tolist() for i in meetings(texts, texts, t))))
        need = {(i, j) for i, y in enumerate(texts) for j, x in enumerate(texts) if len(y) >= len(x) and 100 * (len(y) - far[i][j]) >= t * len(y)}
        assert need <= got
        if t >= 70:
            assert len(got) < len(texts) ** 2 / 8


def test_chance_meetings_leave_no_rows(spark):
    """Fingerprints that share common grams but are not alike: no plan step may make a row for each meeting."""
    import random

    from reuse_engine.operators import pairing

    draw = random.Random(3)
    grams = ["".join(draw.choice("ABCDEFGHIJKLMNOPQRSTUVWXYZ") for _ in range(2)) for _ in range(40)]
    rows = [("c", "o", f"u{i:04}", "".join(draw.choice(grams) for _ in range(12))) for i in range(600)]
    fps = spark.createDataFrame(rows, "corpus string, origin string, unit_id string, fp string").selectExpr("*", "length(fp) as fp_len", *[f"10L as {c}" for c in pairing.ATTRIBUTES])
    met = pairing.chunk_candidates(fps, "true").count()
    assert met < pairing.qgram_candidates(fps, "true").count() / 20
    assert pairing.similar_pairs(fps).exceptAll(pairing.similar_pairs(fps, how="qgram")).count() == 0
    assert pairing.similar_pairs(fps, how="qgram").exceptAll(pairing.similar_pairs(fps, how="band")).count() == 0


def test_recursive_query_follows_long_paths(spark):
    """A path longer than six steps, one of several local minima, and a clique with many walks."""
    from reuse_engine.plans.surround import recursive_labels

    path = [(f"p{i:03}", f"p{i + 1:03}") for i in range(150)]
    zigzag = [(f"z{(i * 7) % 23:02}", f"z{(i + 1) * 7 % 23:02}") for i in range(22)]
    clique = [(f"c{i:02}", f"c{j:02}") for i in range(30) for j in range(i + 1, 30)]
    got = {r["v"]: r["l"] for r in recursive_labels(spark, spark.createDataFrame(path + zigzag + clique, "a string, b string")).collect()}
    assert got == {v: {"p": "p000", "z": "z00", "c": "c00"}[v[0]] for e in path + zigzag + clique for v in e}


def test_locality_reads_the_given_programs(spark):
    """An edit of one function changes one symbol at most, on every given program."""
    from reuse_engine.plans.catalog import QUERIES
    from tests.conftest import SMALL

    rows = QUERIES["m15_locality"](spark, SMALL)
    assert rows.count() == QUERIES["m14_features"](spark, SMALL).where("corpus = 'vm'").count() > 1
    assert rows.where("n_changed > 1 or length(fp_a) <> length(fp_b)").count() == 0


def test_locality_has_a_row_for_each_unit(spark):
    """Units carry no text; their programs are made again, once for each unit however many copies it has."""
    from reuse_engine.plans import methods
    from reuse_engine.plans.catalog import QUERIES
    from tests.conftest import SMALL

    assert "tok" not in methods.fingers_of(spark, SMALL, ["vm"]).columns
    rows = [r["unit_id"] for r in QUERIES["m15_locality"](spark, SMALL).collect()]
    assert sorted(rows) == sorted(r["unit_id"] for r in methods.fingers_of(spark, SMALL, ["vm"]).collect())


def test_sample_of_pairs_is_taken_where_they_meet(spark):
    """What a cell leaves holds the first pairs of every bin in hash order, though far fewer pairs than are compared."""
    import random
    from hashlib import md5

    from reuse_engine.operators import pairing

    draw = random.Random(3)
    rows = [("c", "o", f"u{k}", "".join(draw.choice("ABCD") for _ in range(draw.randint(8, 12)))) for k in range(150)]
    fps = spark.createDataFrame(rows, "corpus string, origin string, unit_id string, fp string").selectExpr("*", "length(fp) as fp_len", *[f"cast(length(fp) as bigint) as {c}" for c in pairing.ATTRIBUTES])
    first = {}
    for r in pairing.scored(pairing.candidate_pairs(fps, "band", "length")).collect():
        first.setdefault(min(r["score_bp"] // 1000, 9), []).append((md5(f"{r['a']}|{r['b']}".encode()).hexdigest(), r["a"], r["b"], r["score_bp"]))
    n = sum(map(len, first.values()))
    got = [tuple(r) for r in pairing.sample_pairs(fps, 4).select("a", "b", "score_bp").collect()]
    assert len(got) == len(set(got)) < n // 4
    assert {t[1:] for pairs in first.values() for t in sorted(pairs)[:4]} <= set(got)


def test_pairs_are_not_dealt_again(spark, monkeypatch):
    """Pairs leave the cells where they meet as they are, also those of a fingerprint that more units have than travel together."""
    import random

    from reuse_engine.operators import chunks, pairing

    monkeypatch.setattr(pairing, "MEMBERS", 5)
    monkeypatch.setattr(chunks, "OUT", 64)
    draw = random.Random(4)
    texts = [*["ABCDEFGH"] * 23, *["ABCDEFGX"] * 3, *["".join(draw.choice("ABC") for _ in range(draw.randint(1, 9))) for _ in range(60)]]
    rows = [("c", "o", f"u{k}", t, 5 + k % 4) for k, t in enumerate(texts)]
    fps = spark.createDataFrame(rows, "corpus string, origin string, unit_id string, fp string, n_ops long")
    fps = fps.selectExpr("*", "length(fp) as fp_len", *[f"n_ops as {c}" for c in pairing.ATTRIBUTES if c != "n_ops"])
    made = pairing.similar_pairs(fps)
    got = sorted(map(tuple, made.collect()))
    assert got == sorted(map(tuple, pairing.similar_pairs(fps, how="theta").collect())) and len(got) > 200
    plan = made._jdf.queryExecution().optimizedPlan().toString()
    assert plan.index("MapInArrow") < plan.index("Join") and "Join" not in plan[: plan.index("MapInArrow")]


def test_distances_of_many_pairs():
    import random

    import numpy as np

    from reuse_engine.operators import chunks

    def slow(a, b):
        last = list(range(len(b) + 1))
        for i, x in enumerate(a, 1):
            row = [i]
            for j, y in enumerate(b, 1):
                row.append(min(last[j] + 1, row[-1] + 1, last[j - 1] + (x != y)))
            last = row
        return last[-1]

    draw = random.Random(1)
    many = "".join(map(chr, range(0x4E00, 0x4E00 + 3000)))
    for letters, low, high in (("ab", 1, 10), ("abcdef", 55, 70), ("abc", 120, 200), (many, 1, 140)):
        ys, xs = (["".join(draw.choices(letters, k=draw.randint(low, high))) for _ in range(n)] for n in (12, 9))
        i, j = np.divmod(np.arange(12 * 9), 9)
        want = [slow(ys[a], xs[b]) for a, b in zip(i, j)]
        for dense in (1 << 22, 0):
            chunks.DENSE, kept = dense, chunks.DENSE
            assert chunks.distances(chunks._Texts(ys), chunks._Texts(xs), i, j).tolist() == want
            chunks.DENSE = kept


def test_few_long_texts_are_measured_in_little_time():
    """Pairs of which every second text takes another number of words: a column of tables at a time took minutes."""
    import random
    import time

    from reuse_engine.operators import chunks

    draw = random.Random(3)
    texts = ["".join(draw.choices("ABCDEFGHIJKLMNOPQRSTUVWXYZ", k=m)) for m in range(2_000, 5_000, 150)]
    near = [t[:700] + t[701:1_500] + "一" + t[1_500:] + "一二" for t in texts]
    ys, xs = chunks._Texts(near), chunks._Texts(texts)
    i = np.arange(len(texts))
    began = time.process_time()
    assert chunks.distances(ys, xs, i, i).tolist() == [4] * len(texts)
    assert time.process_time() - began < 20


def test_distances_agree_however_they_are_measured():
    import random

    from reuse_engine.operators import chunks

    draw = random.Random(5)
    texts = chunks._Texts(["".join(draw.choices("ab一😀", k=m)) for m in (1, 2, 63, 64, 65, 127, 128, 129, 200)])
    i, j = np.divmod(np.arange(81), 9)
    kept, got = chunks.FEW, []
    for chunks.FEW in (0, 1 << 30):
        got.append(chunks.distances(texts, texts, i, j).tolist())
    chunks.FEW = kept
    assert got[0] == got[1] and not any(got[0][::10])


def test_long_chance_meetings_are_left_out_before_they_are_measured():
    """Long texts of the same symbols in another order share chunks and counts, but not what follows what."""
    import random

    from reuse_engine.operators.chunks import meetings

    draw = random.Random(9)
    texts = ["".join(draw.choices("ABCDEFGHIJKLMNOPQRSTUVWXYZabcdefghijklmnopqrstuvwxyz", k=600)) for _ in range(60)]
    y, x = meetings(texts, texts, 70)
    assert list(y) == list(x) == list(range(60))


def test_chunk_pairs_are_measured_in_their_cells(spark):
    """Long runs of few symbols: what leaves a cell has reached the threshold, and cells are not put together by bytes."""
    from reuse_engine.operators.chunks import chunk_pairs
    from reuse_engine.operators.pairing import length_bucket

    texts = {"a": "A" * 60 + "B" * 40, "b": "B" * 40 + "A" * 60, "c": "A" * 62 + "B" * 45, "d": "A" * 40 + "C" * 60}
    rows = spark.createDataFrame([("x", "o", k, v, len(v)) for k, v in texts.items()], "corpus string, origin string, unit_id string, fp string, fp_len int")
    made = chunk_pairs(rows, 70, lambda n: length_bucket(n, 70))
    assert [(r["a"], r["b"], r["dist"]) for r in made.collect()] == [("a", "c", 7)]
    assert made.rdd.getNumPartitions() == int(spark.conf.get("spark.sql.shuffle.partitions"))


def test_texts_of_pairs_are_sent_by_blocks(spark):
    """Distances of long texts over a grid: every pair once, copies and empty texts too, and no row with both texts of a pair."""
    from reuse_engine.operators import chunks

    texts = {"a": "xy" * 50, "b": "xy" * 49, "c": "", "d": "xy" * 50}
    held = spark.createDataFrame([("o", k, v) for k, v in texts.items()], "origin string, id string, text string")
    pairs = spark.createDataFrame([("o", x, y) for x in texts for y in texts if x < y], "origin string, a string, b string")
    made = chunks.text_distances(pairs, held)
    got = {(r["a"], r["b"]): (r["full_dist"], r["full_len"]) for r in made.collect()}
    assert got == {("a", "b"): (2, 100), ("a", "c"): (100, 100), ("a", "d"): (0, 100), ("b", "c"): (98, 98), ("b", "d"): (2, 100), ("c", "d"): (100, 100)}


def test_neighbours_of_deployments_meet_once_for_each_fingerprint(spark):
    """New and known fingerprints, with copies among both: the plan has no join that forms all pairs of a length band."""
    from reuse_engine.streaming.streams import known_neighbours

    new = spark.createDataFrame([("o", "d1", "ABCDEFGHIJ", 10, 10), ("o", "d2", "ABCDEFGHIJ", 10, 10), ("o", "d3", "ZZZZZZZZZZ", 10, 10), ("o", "d4", "", 0, 0)], "origin string, artifact_id string, fp string, fp_len int, n_ops long")
    old = spark.createDataFrame([("o", "u1", "ABCDEFGHIJ", 10, 10), ("o", "u2", "ABCDEFGHXX", 10, 10), ("o", "u3", "ABCDEFGHIJ", 10, 20), ("p", "u4", "ABCDEFGHIJ", 10, 10)], "origin string, unit_id string, fp string, fp_len int, n_ops long")
    made = known_neighbours(new, old)
    assert sorted(map(tuple, made.collect())) == [("d1", "u1", 10000), ("d1", "u2", 8000), ("d2", "u1", 10000), ("d2", "u2", 8000)]
    assert "levenshtein" not in made._jdf.queryExecution().executedPlan().toString()


def test_ablation_counts_pairs_without_a_row_for_each(spark):
    """Counts of every rule against the plans that form the pairs; rows of equal lengths, attributes at the ratio and copies too."""
    rows = [("c", "o", f"u{n}", "ABCDEFGHIJ"[: 2 + n % 9] * (1 + n % 2), (2 + n % 9) * (1 + n % 2), 7 + n % 5, n % 4, 10 * (n % 3), 1, n % 7, 70 + 10 * (n % 4)) for n in range(60)]
    fps = spark.createDataFrame(rows, "corpus string, origin string, unit_id string, fp string, fp_len int, n_ops long, n_pieces long, n_distinct_ops long, n_terminators long, n_operand_bytes long, n_bytes long")
    for rule in ("none", "length", "attrs", "fp_len", "bag"):
        made = pairing.left_counts(fps, rule)
        want = pairing.candidate_pairs(fps, "theta" if rule == "none" else "band", rule).count()
        assert [tuple(r) for r in made.collect()] == [("c", want)], rule
        assert "_a" not in made._jdf.queryExecution().executedPlan().toString()


@pytest.mark.parametrize("corpus", ["documents", "pages", "scripts_week"])
@pytest.mark.parametrize("method", ["block", "random"])
def test_fingerprints_deal_out_no_text(spark, corpus, method):
    from reuse_engine.operators import fingerprints
    from reuse_engine.plans.methods import texts_of, units_of
    from reuse_engine.sources.artifacts import CORPORA, artifacts

    made = fingerprints.printed_units(artifacts(spark, SMALL, corpus, lambda rows: fingerprints.prints(rows, CORPORA[corpus], method=method)))
    plan = made._jdf.queryExecution().optimizedPlan().toString()
    above = plan.split("Join")[0] if corpus != "scripts_week" else ""  # programs are made from shuffled events
    assert "tok#" not in above and "payload#" not in above
    want = fingerprints.fingers(units_of(spark, SMALL, [corpus]), CORPORA[corpus], method)
    rows = lambda df: sorted(map(str, df.select(*want.columns).collect()))
    assert rows(texts_of(spark, SMALL, corpus, method=method)) == rows(want)
    assert rows(made.join(want.select("unit_id", "tok"), "unit_id")) == rows(want)


def test_findings_deal_out_no_text(spark):
    from reuse_engine.plans import workloads

    plan = workloads.document_payloads(spark, SMALL)[1]._jdf.queryExecution().optimizedPlan().toString()
    assert "Join" not in plan and "events" not in plan


def test_bundle_pairs_without_a_choice_need_no_solver(spark, monkeypatch):
    from reuse_engine.operators import assignment, bundles

    rows = [("p", "q", "1", "a", 7000, 3, 4), ("p", "q", "2", "b", 9000, 3, 4), ("p", "r", "1", "c", 9000, 3, 2), ("p", "r", "1", "d", 8000, 3, 2), ("p", "r", "2", "c", 8500, 3, 2)]
    w = spark.createDataFrame(rows, "ua string, ub string, i string, j string, w long, n_a long, n_b long")
    got = {algo: sorted(map(tuple, bundles.match_bundles(w, algo).collect())) for algo in ("optimal", "greedy")}
    assert got["optimal"] == [("p", "q", 3, 4, 16000, 2), ("p", "r", 3, 2, 16500, 2)]
    assert got["greedy"] == [("p", "q", 3, 4, 16000, 2), ("p", "r", 3, 2, 9000, 1)]

    def refuse(algo):
        return lambda pdf: 1 / 0

    monkeypatch.setattr(bundles, "_solve", refuse)
    assert bundles.match_bundles(w.where("ub = 'q'")).count() == 1
