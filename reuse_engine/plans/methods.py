"""Methods, variants and baselines of the analysis as named queries."""

from __future__ import annotations

from functools import reduce

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from reuse_engine.functions.symbols import piece_hash, score_bp, symbol
from reuse_engine.operators import fingerprints, homogeneity, pairing, preprocess
from reuse_engine.operators.chunks import text_distances
from reuse_engine.plans import sqltext as S
from reuse_engine.plans.registry import query
from reuse_engine.sources.artifacts import CORPORA, artifacts, payloads
from reuse_engine.storage import few_broadcast, join_few, materialize, shared_table


def union(frames: list[DataFrame]) -> DataFrame:
    return reduce(DataFrame.unionByName, frames)


def norm_of(spark: SparkSession, d: str, corpora: list[str], stages: tuple[str, ...] = preprocess.STAGES) -> DataFrame:
    return union([preprocess.corpus_normalized(artifacts(spark, d, c), c, stages) for c in corpora])


def units_of(spark: SparkSession, d: str, corpora: list[str], stages: tuple[str, ...] = preprocess.STAGES) -> DataFrame:
    return preprocess.units(norm_of(spark, d, corpora, stages))


def fingers_of(spark: SparkSession, d: str, corpora: list[str], stages: tuple[str, ...] = preprocess.STAGES, **kw) -> DataFrame:
    """Written once for each corpus and shared by all queries: far smaller than the payloads, of which no column is kept."""
    key = (stages, tuple(sorted(kw.items())))
    return union([shared_table(spark, d, "fingers", (c, *key), lambda c=c: fingerprints.printed_units(prints_of(spark, d, c, stages, **kw))) for c in corpora])


def prints_of(spark: SparkSession, d: str, c: str, stages: tuple[str, ...] = preprocess.STAGES, **kw) -> DataFrame:
    """Artifacts of a corpus with hash and fingerprint in place of the payload; those of the usual stages are written once."""
    made = lambda: artifacts(spark, d, c, lambda rows: fingerprints.prints(rows, CORPORA[c], stages, **kw))
    return shared_table(spark, d, "prints", (c,), made) if stages == preprocess.STAGES and not kw else made()


def texts_of(spark: SparkSession, d: str, c: str, **kw) -> DataFrame:
    """:func:`fingers_of` one corpus with ``tok``, made again from the payloads of the units' artifacts."""
    fps = fingers_of(spark, d, [c], **kw)
    tokens = fingerprints.tokens_of(payloads(spark, d, c), CORPORA[c]).withColumnRenamed("artifact_id", "unit_id")
    rows = tokens.join(few_broadcast(fps), ["unit_id", "token_hash"])
    keys = prints_of(spark, d, c).groupBy("artifact_id").count().where("count > 1")
    once = rows.dropDuplicates(["corpus", "origin", "token_hash"]) if keys.head(1) else rows
    return once.select(*fps.columns, "tok")


def pairs_of(spark: SparkSession, d: str, corpora: list[str], threshold: int = 70) -> DataFrame:
    """The stored table of similar pairs under the length rule, by corpus; all later operators read it."""
    made = lambda c: pairing.similar_pairs(fingers_of(spark, d, [c]), threshold)
    return union([shared_table(spark, d, "pairs", (c, threshold), lambda c=c: made(c)) for c in corpora])


ALL = list(CORPORA)
MAIN = ["documents", "pages", "scripts_week"]
VM = ["vm", "pages", "documents"]


@query("m01_strip_prefix", S.with_(S.artifacts(VM), f"""SELECT artifact_id, corpus, md5(body) AS body_hash, body <> payload AS had_prefix FROM (
  SELECT *, CASE corpus WHEN 'vm' THEN {S._PREFIX['vmhex'].format('payload')} WHEN 'pages' THEN {S._PREFIX['markup'].format('payload')} ELSE payload END AS body FROM art)"""))
def _m01(spark, d):
    return union([preprocess.strip_prefix(artifacts(spark, d, c), CORPORA[c]) for c in VM]).select("artifact_id", "corpus", F.md5("body").alias("body_hash"), "had_prefix")


@query("m02_strip_trailer", S.with_(S.artifacts(VM), f"""SELECT artifact_id, corpus, md5(body) AS body_hash, body <> payload AS had_trailer FROM (
  SELECT *, CASE corpus WHEN 'vm' THEN {S._TRAILER['vmhex'].format('payload')} WHEN 'pages' THEN {S._TRAILER['markup'].format('payload')} ELSE {S._TRAILER['prose'].format('payload')} END AS body FROM art)"""))
def _m02(spark, d):
    return union([preprocess.strip_trailer(artifacts(spark, d, c), CORPORA[c]) for c in VM]).select("artifact_id", "corpus", F.md5("body").alias("body_hash"), "had_trailer")


def _dedupe(by: str):
    def run(spark: SparkSession, d: str) -> DataFrame:
        return preprocess.dedupe(norm_of(spark, d, ALL), by)

    sql = S.with_(S.normalized(ALL), f"""SELECT corpus, origin, {by}, count(*) AS n_artifacts, count(DISTINCT creator) AS n_creators,
      first(artifact_id ORDER BY coalesce(deployed_us, {S.LATEST}), artifact_id) AS first_artifact FROM norm GROUP BY ALL""")
    return sql, run


for _name, _by in (("m03_runtime_hash_dedupe", "runtime_hash"), ("m06_token_hash_dedupe", "token_hash")):
    _sql, _run = _dedupe(_by)
    query(_name, _sql)(_run)


@query("m04_tokenize", S.with_(S.normalized(["vm", "rows", "scripts"]), f"""SELECT corpus, artifact_id, len(toks) AS n_tokens, toks[1] AS first_token, toks[len(toks)] AS last_token
  FROM (SELECT *, CASE corpus WHEN 'scripts' THEN {S.token_list('script')} ELSE {S.token_list('vmhex')} END AS toks FROM norm)"""))
def _m04(spark, d):
    parts = []
    for c in ("vm", "rows", "scripts"):
        t = norm_of(spark, d, [c]).withColumn("t", fingerprints.token_array(CORPORA[c]))
        parts.append(t.select("corpus", "artifact_id", F.size("t").cast("bigint").alias("n_tokens"), F.get("t", F.lit(0)).alias("first_token"), F.try_element_at("t", F.lit(-1)).alias("last_token")))
    return union(parts)


@query("m05_erase_operands", S.with_(S.normalized(ALL), "SELECT corpus, artifact_id, token_hash, length(tok) AS n_chars FROM norm"))
def _m05(spark, d):
    return norm_of(spark, d, ALL).select("corpus", "artifact_id", "token_hash", F.length("tok").cast("bigint").alias("n_chars"))


@query("m07_split_by_origin", S.with_(S.artifacts(ALL), "SELECT corpus, origin, count(*) AS n_artifacts, count(DISTINCT bundle_id) AS n_bundles FROM art GROUP BY ALL"))
def _m07(spark, d):
    return union([artifacts(spark, d, c).select("corpus", "origin", "bundle_id") for c in ALL]).groupBy("corpus", "origin").agg(
        F.count("*").alias("n_artifacts"), F.countDistinct("bundle_id").alias("n_bundles")
    )


_REDEPLOY = S.with_(S.normalized(["vm"]), "SELECT runtime_hash, count(DISTINCT raw_hash) AS n_raw, count(*) AS n_artifacts FROM norm GROUP BY 1 HAVING count(DISTINCT raw_hash) > 1")


@query("m08_redeploy_check", _REDEPLOY)
@query("w21_redeploy", _REDEPLOY)
def _m08(spark, d):
    return preprocess.redeploys(norm_of(spark, d, ["vm"]))


_STAGE_SETS = {"none": (), "prefix": ("prefix",), "prefix_trailer": ("prefix", "trailer"), "all": ("prefix", "trailer", "operands")}


def _ablation_sql() -> str:
    parts = [f"SELECT '{n}' AS stages, corpus, count(DISTINCT token_hash) AS n_units FROM ({S.with_(S.normalized(['vm', 'pages', 'documents'], st), 'SELECT corpus, token_hash FROM norm')}) GROUP BY ALL" for n, st in _STAGE_SETS.items()]
    return " UNION ALL ".join(parts)


@query("m09_stage_variants", _ablation_sql())
def _m09(spark, d):
    return union([
        norm_of(spark, d, ["vm", "pages", "documents"], st).groupBy("corpus").agg(F.countDistinct("token_hash").alias("n_units")).select(F.lit(n).alias("stages"), "corpus", "n_units")
        for n, st in _STAGE_SETS.items()
    ])


@query("m10_cut_blocks", S.with_(S.fingers(ALL), "SELECT corpus, origin, unit_id, n_pieces, md5(coalesce(array_to_string(pieces, '|'), '')) AS pieces_hash FROM finger"))
def _m10(spark, d):
    cut = [fingerprints.pieces(units_of(spark, d, [c]), CORPORA[c]) for c in ALL]
    return union(cut).select("corpus", "origin", "unit_id", F.size("pieces").cast("bigint").alias("n_pieces"), F.md5(F.array_join("pieces", "|")).alias("pieces_hash"))


_SCRIPT_PIECES = "SELECT DISTINCT unnest(pieces) AS piece FROM finger"


@query("m11_piece_hash", S.with_(S.fingers(["scripts", "vm"]), f"SELECT piece, ('0x' || substr(md5(piece), 1, 8))::BIGINT AS digest32, ('0x' || substr(md5(piece), 1, 4))::BIGINT AS digest16 FROM ({_SCRIPT_PIECES})"))
def _m11(spark, d):
    return _piece_rows(spark, d).select("piece", piece_hash(F.col("piece")).alias("digest32"), piece_hash(F.col("piece"), digest_chars=4).alias("digest16"))


def _piece_rows(spark, d):
    cut = [fingerprints.pieces(units_of(spark, d, [c]), CORPORA[c]).select(F.explode_outer("pieces").alias("piece")) for c in ("scripts", "vm")]
    return union(cut).where("piece is not null").distinct()


@query("m12_base64_char", S.with_(S.fingers(["scripts", "vm"]), f"SELECT {S.symbol('piece')} AS symbol, count(*) AS n_pieces FROM ({_SCRIPT_PIECES}) GROUP BY 1"))
def _m12(spark, d):
    return _piece_rows(spark, d).groupBy(symbol(piece_hash(F.col("piece"))).alias("symbol")).agg(F.count("*").alias("n_pieces"))


def _fp_query(name: str, corpora: list[str], **kw) -> None:
    sql_kw = {{"digest_chars": "chars"}.get(k, k): v for k, v in kw.items() if k != "algo"}
    sql = None if kw.get("algo") or kw.get("method") == "rolling" else S.with_(S.fingers(corpora, **sql_kw), "SELECT corpus, origin, unit_id, fp, fp_len::BIGINT AS fp_len, n_dup FROM finger")

    def run(spark: SparkSession, d: str) -> DataFrame:
        made = union([fingerprints.fingers(units_of(spark, d, [c]), CORPORA[c], **kw) for c in corpora])
        return made.select("corpus", "origin", "unit_id", "fp", F.col("fp_len").cast("bigint").alias("fp_len"), "n_dup")

    query(name, sql)(run)


_fp_query("m13_fingerprint", ALL)
_fp_query("m13_fingerprint_digest4", ["documents", "vm"], digest_chars=4)
_fp_query("m13_fingerprint_crc32", ["documents", "vm"], algo="crc32")
_fp_query("m13_fingerprint_xxhash64", ["documents", "vm"], algo="xxhash64")
_fp_query("m13_fingerprint_fnv1a32", ["documents", "vm"], algo="fnv1a32")
_fp_query("b03_fixed_step", MAIN, method="fixed", step=7)
_fp_query("b04_random_boundary", MAIN, method="random")
_fp_query("b05_rolling_trigger", MAIN, method="rolling")


@query("m14_features", S.with_(S.fingers(ALL), "SELECT corpus, origin, unit_id, n_ops, n_pieces, n_distinct_ops, n_terminators, n_operand_bytes, n_bytes FROM finger"))
def _m14(spark, d):
    return union([fingerprints.fingers(units_of(spark, d, [c]), CORPORA[c]) for c in ALL]).select("corpus", "origin", "unit_id", *fingerprints.FEATURES)


def _fixture_sql(rows: dict[str, str]) -> str:
    return "prog(name, runtime) AS (VALUES " + ", ".join(f"('{k}', '{v}')" for k, v in rows.items()) + ")"


def _vm_fp_sql(src: str) -> str:
    return f"SELECT name, tok, pieces, {S.symbols('pieces')} AS fp FROM (SELECT *, {S.pieces_of('vmhex')} AS pieces FROM (SELECT name, {S._tokens('vmhex', 'runtime', True)} AS tok FROM {src}))"


def _vm_fps(spark: SparkSession, rows: dict[str, str]) -> DataFrame:
    df = spark.createDataFrame(list(rows.items()), "name string, runtime string")
    from reuse_engine.functions.dialects import DIALECTS
    from reuse_engine.functions.symbols import fingerprint

    vm = DIALECTS["vmhex"]
    cut = df.withColumn("tok", vm.tokens(F.col("runtime"), True)).withColumn("pieces", vm.pieces(F.col("tok")))
    return cut.withColumn("fp", fingerprint(F.col("pieces")))


#: One instruction that an edit puts before the first function of a program. Fixed value.
LOCALITY_EDIT = "5b"


@query("m15_locality", S.with_(S.fingers(["vm"]), f"""SELECT origin, unit_id, fp_a, fp_b, len(list_filter(range(1, greatest(length(fp_a), length(fp_b)) + 1), lambda i: fp_a[i] <> fp_b[i])) AS n_changed
  FROM (SELECT origin, unit_id, fp_a, {S.symbols('pieces')} AS fp_b FROM (SELECT *, {S.pieces_of('vmhex')} AS pieces FROM (SELECT origin, unit_id, fp AS fp_a, '{LOCALITY_EDIT} ' || tok AS tok FROM finger)))"""))
def _m15(spark, d):
    """Every program of byte code with one function edited: symbols of the fingerprint that change."""
    from reuse_engine.functions.dialects import DIALECTS
    from reuse_engine.functions.symbols import fingerprint

    fps = texts_of(spark, d, "vm").withColumnRenamed("fp", "fp_a")
    edited = DIALECTS["vmhex"].pieces(F.concat(F.lit(LOCALITY_EDIT + " "), F.col("tok")))
    both = fps.select("origin", "unit_id", "fp_a", fingerprint(edited).alias("fp_b"))
    return both.withColumn("n_changed", fingerprints.symbol_diff(F.col("fp_a"), F.col("fp_b")).cast("bigint"))


@query("m16_collision_share", S.with_(S.fingers(["documents"]), f"""SELECT sum(n)::BIGINT AS n_pieces, count(*) AS n_symbols, sum(n * (n - 1) // 2)::BIGINT AS n_colliding,
  ((10000 * sum(n * (n - 1) // 2)) // greatest(sum(n) * (sum(n) - 1) // 2, 1))::BIGINT AS rate_bp, (10000 // 64)::BIGINT AS expected_bp FROM (SELECT {S.symbol('piece')} AS s, count(*) AS n FROM ({_SCRIPT_PIECES}) GROUP BY 1)"""))
def _m16_share(spark, d):
    return fingerprints.collision_rate(fingerprints.collision_stats(units_of(spark, d, ["documents"]), "prose"))


@query("m16_collision_rate", S.with_(S.fingers(["documents"]), f"SELECT {S.symbol('piece')} AS symbol, count(*) AS n_pieces FROM ({_SCRIPT_PIECES}) GROUP BY 1"))
def _m16(spark, d):
    return fingerprints.collision_stats(units_of(spark, d, ["documents"]), "prose")


@query("m17_compression", S.with_(S.fingers(ALL), "SELECT corpus, origin, count(*) AS n_units, sum(fp_len)::BIGINT AS symbols, sum(n_bytes)::BIGINT AS bytes, (10000 * sum(fp_len)::BIGINT) // sum(n_bytes)::BIGINT AS ratio_bp FROM finger GROUP BY ALL"))
def _m17(spark, d):
    return fingerprints.compression(union([fingerprints.fingers(units_of(spark, d, [c]), CORPORA[c]) for c in ALL]))


@query("b01_exact_hash", S.with_(S.normalized(["documents", "scripts_week"]), """SELECT corpus, artifact_id AS member, rep, n::BIGINT AS n_group FROM (
  SELECT corpus, artifact_id, min(artifact_id) OVER w AS rep, count(*) OVER w AS n FROM norm WINDOW w AS (PARTITION BY corpus, origin, runtime_hash)) WHERE n >= 2"""))
def _b01(spark, d):
    """Groups of equal runtimes as members of a representative: all pairs of a group follow from them, and are not formed."""
    rows = norm_of(spark, d, ["documents", "scripts_week"]).select("corpus", F.struct("corpus", "origin", "runtime_hash").alias("at"), "artifact_id")
    rows = materialize(rows, "exact-rows")
    groups = rows.groupBy("at").agg(F.min("artifact_id").alias("rep"), F.count("*").alias("n_group")).where("n_group >= 2")
    return join_few(rows, materialize(groups, "exact-groups"), "at", F.xxhash64("artifact_id")).select("corpus", F.col("artifact_id").alias("member"), "rep", "n_group")


@query("b02_full_edit", S.with_(S.pairs(["scripts_week"]), "SELECT p.a, p.b, levenshtein(x.tok, y.tok) AS full_dist, greatest(length(x.tok), length(y.tok)) AS full_len, p.score_bp FROM pair p JOIN finger x ON x.unit_id = p.a AND x.origin = p.origin JOIN finger y ON y.unit_id = p.b AND y.origin = p.origin"))
def _b02(spark, d):
    fps = texts_of(spark, d, "scripts_week")
    pairs = pairs_of(spark, d, ["scripts_week"])
    both = text_distances(pairs.select("origin", "a", "b", "score_bp"), fps.select("origin", F.col("unit_id").alias("id"), F.col("tok").alias("text")))
    return both.select("a", "b", "full_dist", "full_len", "score_bp")


_PAIR_COLS = "corpus, origin, a, b, la::BIGINT AS la, lb::BIGINT AS lb, dist::BIGINT AS dist, max_len::BIGINT AS max_len, score_bp::BIGINT AS score_bp"


def long_pairs(df: DataFrame) -> DataFrame:
    return df.select("corpus", "origin", "a", "b", *[F.col(c).cast("bigint").alias(c) for c in ("la", "lb", "dist", "max_len", "score_bp")])


def _pair_query(name: str, corpora: list[str], how: str, prune: str | None, threshold: int = 70, strict: bool = False, exact: bool = True, stages=preprocess.STAGES) -> None:
    rule = "fp_len" if prune == "bag" else prune
    sql = S.with_(S.pairs(corpora, threshold, rule, strict, stages=stages), f"SELECT {_PAIR_COLS} FROM pair") if exact else None

    def run(spark: SparkSession, d: str) -> DataFrame:
        return long_pairs(pairing.similar_pairs(fingers_of(spark, d, corpora, stages), threshold, not strict, how, prune))

    query(name, sql)(run)


_pair_query("w09_similar_pairs", ["documents"], "chunk", "length")
_pair_query("w09s_similar_pairs_strict", ["documents"], "chunk", "length", strict=True)
_pair_query("m29_pairs", MAIN, "chunk", "length")
_pair_query("b06_no_prune", ["documents", "pages"], "theta", None)
_pair_query("b07_no_erase", ["documents", "pages"], "chunk", "length", stages=("prefix", "trailer"))
_pair_query("b08_no_strip", ["documents", "pages", "vm"], "chunk", "length", stages=("operands",))
_pair_query("m22_prune_length", ["documents", "pages"], "band", "length")
_pair_query("m23_prune_attrs", ["documents", "pages"], "band", "attrs")
_pair_query("m24_prune_fp_len", ["documents", "pages"], "band", "fp_len")
_pair_query("m25_bag_bound", ["documents", "pages"], "band", "bag")
_pair_query("m26_qgram_count", ["documents", "pages"], "qgram", None)
_pair_query("m27_band_join", MAIN, "band", "length")
_pair_query("m28_lsh", ["documents", "pages"], "minhash", "length", exact=False)


@query("m20_edit_distance", S.with_(S.compared(["pages"]), "SELECT a, b, dist::BIGINT AS dist, CASE WHEN dist <= 3 THEN dist ELSE -1 END::BIGINT AS within_3 FROM comp"))
def _m20(spark, d):
    c = pairing.candidate_pairs(fingers_of(spark, d, ["pages"]), "band", "length")
    return c.select(F.col("unit_id_a").alias("a"), F.col("unit_id_b").alias("b"), F.levenshtein("fp_a", "fp_b").cast("bigint").alias("dist"), F.levenshtein("fp_a", "fp_b", 3).cast("bigint").alias("within_3"))


@query("m21_score", "SELECT d AS dist, m AS max_len, (10000 * (m - d)) // m AS score_bp, 100 * (m - d) >= 70 * m AS inclusive, 100 * (m - d) > 70 * m AS strict FROM range(1, 41) a(m), range(0, 41) b(d) WHERE d <= m")
def _m21(spark, d):
    m, dist = spark.range(1, 41).toDF("max_len"), spark.range(0, 41).toDF("dist")
    both = m.join(dist, F.col("dist") <= F.col("max_len"))
    return both.select("dist", "max_len", score_bp(F.col("dist"), F.col("max_len")).alias("score_bp"), F.expr("100 * (max_len - dist) >= 70 * max_len").alias("inclusive"), F.expr("100 * (max_len - dist) > 70 * max_len").alias("strict"))


@query("m30_pair_reuse", S.with_(S.compared(["pages"]), "SELECT t AS threshold, count(*) AS n_pairs FROM comp, range(40, 100, 10) r(t) WHERE 100 * (max_len - dist) >= t * max_len GROUP BY t"))
def _m30(spark, d):
    """One stored table of pairs from 40 up serves every threshold."""
    stored = materialize(pairing.similar_pairs(fingers_of(spark, d, ["pages"]), 40, True, "band", "length"), "pairs", ["origin"])
    hit = F.filter(F.sequence(F.lit(40), F.lit(90), F.lit(10)), lambda t: 100 * (F.col("max_len") - F.col("dist")) >= t * F.col("max_len"))
    return stored.select(F.explode(hit).alias("t")).groupBy(F.col("t").cast("bigint").alias("threshold")).agg(F.count("*").alias("n_pairs"))


@query("m40_graph", S.with_(S.pairs(["documents"]), "SELECT p AS vertex, count(*) AS degree, sum(score_bp)::BIGINT AS weight FROM (SELECT a AS p, score_bp FROM pair UNION ALL SELECT b, score_bp FROM pair) GROUP BY 1"))
def _m40(spark, d):
    g = homogeneity.similarity_graph(pairs_of(spark, d, ["documents"]))
    ends = g.select(F.col("a").alias("vertex"), "score_bp").unionByName(g.select(F.col("b").alias("vertex"), "score_bp"))
    return ends.groupBy("vertex").agg(F.count("*").alias("degree"), F.sum("score_bp").alias("weight"))

