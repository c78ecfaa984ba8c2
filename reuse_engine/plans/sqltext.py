"""SQL text of the analysis for DuckDB: the independent statement of each step."""

from __future__ import annotations

from reuse_engine.functions.dialects import DEPLOY_MARKER, FLOW_BREAKERS, STAGES, TRAILER_BYTES_BETWEEN, TRAILER_END, TRAILER_HEAD, opcode_pattern
from reuse_engine.functions.symbols import ALPHABET
from reuse_engine.operators.findings import PATTERNS
from reuse_engine.operators.pairing import ATTRIBUTES
from reuse_engine.sources.artifacts import CORPORA, CREATION, ENDS, OPCODES

LATEST = 1 << 62
_SPAN = {"day": 86_400_000_000, "week": 7 * 86_400_000_000}


def _steps(period: str, code: str, gap: str) -> str:
    span = _SPAN[period]
    return f"""SELECT user_id, user_id::VARCHAR AS creator, (epoch_us(ts) - epoch_us(ts) % {span}) // 86400000000 AS day,
      string_agg({code}, '{gap}' ORDER BY epoch_us(ts), event_id) AS body, min(epoch_us(ts)) AS deployed_us, sum(round(value * 1000)::BIGINT)::BIGINT AS volume_milli
      FROM events GROUP BY ALL"""


def _script(period: str, corpus: str) -> str:
    code = "substr(event_type, 1, 1) || round(value * 1000)::BIGINT::VARCHAR"
    return f"""SELECT creator || '@' || day::VARCHAR AS artifact_id, CASE WHEN user_id % 2 = 0 THEN 'direct' ELSE 'factory' END AS origin,
      creator, creator AS bundle_id, deployed_us, body AS payload, volume_milli FROM ({_steps(period, code, " ")})"""


def _vm() -> str:
    cases = " ".join(f"WHEN '{k}' THEN '60' || format('{{:02x}}', abs(round(value * 1000)::BIGINT) % 256) || '{b}{ENDS.get(k, '')}'" for k, b in OPCODES.items())
    name = "creator || '@' || day::VARCHAR"
    return f"""SELECT {name} AS artifact_id, CASE WHEN user_id % 2 = 0 THEN 'direct' ELSE 'factory' END AS origin, creator, creator AS bundle_id, deployed_us,
      '{CREATION}{DEPLOY_MARKER}' || body || '{TRAILER_HEAD}20' || md5({name}) || md5({name} || '#') || '{TRAILER_END}' AS payload, volume_milli
      FROM ({_steps("day", f"CASE event_type {cases} ELSE '00' END", "")})"""


_ARTIFACTS = {
    "documents": """SELECT doc_id::VARCHAR AS artifact_id, CASE WHEN lang = 'en' THEN 'direct' ELSE 'factory' END AS origin, source AS creator,
      source || '/' || (doc_id // 80)::VARCHAR AS bundle_id, epoch_us(e.ts) AS deployed_us, coalesce(text, '') AS payload, round(o_totalprice * 1000)::BIGINT AS volume_milli
      FROM documents d LEFT JOIN events e ON e.event_id = d.doc_id LEFT JOIN orders o ON o.o_orderkey = d.doc_id""",
    "pages": """SELECT page_id::VARCHAR AS artifact_id, 'factory' AS origin, regexp_extract(url, '^https?://([^/?#]+)', 1) AS creator,
      regexp_extract(url, '^https?://([^/?#]+)', 1) AS bundle_id, epoch_us(e.ts) AS deployed_us, coalesce(html, '') AS payload, round(e.value * 1000)::BIGINT AS volume_milli
      FROM pages p LEFT JOIN events e ON e.event_id = p.page_id""",
    "scripts": _script("day", "scripts"),
    "scripts_week": _script("week", "scripts_week"),
    "vm": _vm(),
    "conversations": """SELECT conv_id::VARCHAR || '/' || turn::VARCHAR AS artifact_id, CASE WHEN role = 'assistant' THEN 'factory' ELSE 'direct' END AS origin,
      role AS creator, conv_id::VARCHAR AS bundle_id, NULL::BIGINT AS deployed_us, coalesce(text, '') AS payload, NULL::BIGINT AS volume_milli FROM conversations""",
    "rows": """SELECT l_orderkey::VARCHAR AS artifact_id, 'direct' AS origin, any_value(o_custkey)::VARCHAR AS creator, any_value(o_custkey)::VARCHAR AS bundle_id,
      any_value(epoch_us(o_orderdate)) AS deployed_us,
      string_agg(l_returnflag || l_linestatus || ':' || trunc(l_quantity)::BIGINT::VARCHAR, ' ' ORDER BY l_linenumber, l_returnflag, l_linestatus, l_quantity) AS payload,
      sum(round(l_extendedprice * 1000)::BIGINT)::BIGINT AS volume_milli FROM lineitem LEFT JOIN orders ON o_orderkey = l_orderkey GROUP BY l_orderkey""",
    "vectors": """SELECT vec_id::VARCHAR AS artifact_id, 'direct' AS origin, label::VARCHAR AS creator, label::VARCHAR AS bundle_id, NULL::BIGINT AS deployed_us,
      array_to_string([array_to_string(list_transform(embedding[i + 1:i + 6], lambda v: CASE WHEN v > 0 THEN '1' ELSE '0' END), '') FOR i IN range(0, 61, 6)], ' ') AS payload,
      NULL::BIGINT AS volume_milli FROM embeddings""",
}

_PREFIX = {
    "vmhex": f"regexp_replace({{}}, '^(?:[0-9a-f]{{{{2}}}})*?{DEPLOY_MARKER}', '')",
    "markup": "regexp_replace({}, '(?s)^.*?</head>', '')",
}
_TRAILER = {
    "vmhex": f"regexp_replace({{}}, '{TRAILER_HEAD}[0-9a-f]{{{{{2 * TRAILER_BYTES_BETWEEN}}}}}{TRAILER_END}$', '')",
    "prose": r"regexp_replace({}, '(?i)\n[^\n]*(licen[cs]e|rights reserved)[^\n]*\z', '')",
    "markup": "regexp_replace(regexp_replace({}, '(?s)<!--.*?-->', '', 'g'), '(?s)<footer>.*?</footer>', '<footer></footer>', 'g')",
}
_BREAK = "|".join(FLOW_BREAKERS)


def _tokens(dialect: str, c: str, erase: bool) -> str:
    if dialect == "vmhex":
        found = f"regexp_extract_all({c}, '{opcode_pattern()}')"
        return f"array_to_string(list_transform({found}, lambda x: x[1:2]), ' ')" if erase else f"array_to_string({found}, ' ')"
    if dialect == "prose":
        plain = f"regexp_replace(lower({c}), '[0-9]+', '', 'g')" if erase else f"lower({c})"
        return rf"trim(regexp_replace(regexp_replace({plain}, '[ \t]+', ' ', 'g'), '[.!?\n]+', '.', 'g'), ' ')"
    if dialect == "markup":
        pattern = "</?[a-zA-Z][a-zA-Z0-9]*" if erase else "</?[a-zA-Z][^>]*"
        return f"array_to_string(list_transform(regexp_extract_all({c}, '{pattern}'), lambda x: replace(x, ' ', '_')), ' ')"
    if dialect == "script":
        return f"regexp_replace({c}, '[^a-z]', '', 'g')" if erase else c
    if dialect == "rowseq":
        return f"regexp_replace({c}, ':[0-9.]*', '', 'g')" if erase else c
    return c


def _cut(enders: str, glue: str) -> str:
    return rf"list_filter(list_transform(string_split(regexp_replace(tok || ' ', '({enders}) ', '\1|', 'g'), '|'), lambda p: replace(trim(p, ' '), ' ', '{glue}')), lambda p: p <> '')"


_CLOSERS = "</(?:p|li|h1|div|nav|article|footer)"
_PIECES = {
    "vmhex": _cut(_BREAK, ""),
    "prose": "list_filter(list_transform(string_split(tok, '.'), lambda p: trim(p, ' ')), lambda p: p <> '')",
    "markup": _cut(_CLOSERS, " "),
    "script": r"list_filter(string_split(regexp_replace(tok, '([pe])', '\1|', 'g'), '|'), lambda p: p <> '')",
    "rowseq": _cut("[A-Z]F", " "),
    "vector": "list_filter(string_split(tok, ' '), lambda p: p <> '')",
}
_ENDER = {"vmhex": f"(?:{_BREAK})(?: |$)", "prose": "[.]", "markup": f"{_CLOSERS}(?: |$)", "script": "[pe]", "rowseq": "[A-Z]F(?: |$)", "vector": "[01]+(?: |$)"}
_GAP = {"script": ""}


def _count(dialect: str) -> str:
    if dialect == "script":
        return "length(tok)"
    t = "trim(regexp_replace(tok, '[. ]+', ' ', 'g'), ' ')" if dialect == "prose" else "tok"
    return f"CASE WHEN {t} = '' THEN 0 ELSE len(string_split({t}, ' ')) END"


def token_list(dialect: str) -> str:
    return f"CASE WHEN tok = '' THEN []::VARCHAR[] ELSE string_split(tok, '{_GAP.get(dialect, ' ')}') END"


def symbol(p: str, chars: int = 8) -> str:
    return f"substr('{ALPHABET}', (('0x' || substr(md5({p}), 1, {chars}))::BIGINT % 64 + 1)::INT, 1)"


def symbols(pieces: str, chars: int = 8) -> str:
    return f"coalesce(array_to_string(list_transform({pieces}, lambda p: {symbol('p', chars)}), ''), '')"


def artifacts(corpora: list[str]) -> str:
    body = " UNION ALL ".join(f"SELECT '{c}' AS corpus, * FROM ({_ARTIFACTS[c]})" for c in corpora)
    return f"art AS MATERIALIZED ({body})"


def normalized(corpora: list[str], stages: tuple[str, ...] = STAGES) -> str:
    """CTEs art and norm."""
    parts = []
    for c in corpora:
        d = CORPORA[c]
        body = _PREFIX.get(d, "{}").format("payload") if "prefix" in stages else "payload"
        run = _TRAILER.get(d, "{}").format("body") if "trailer" in stages else "body"
        parts.append(
            f"""SELECT *, {_tokens(d, 'runtime', 'operands' in stages)} AS tok FROM (SELECT *, {run} AS runtime FROM (SELECT *, {body} AS body FROM art WHERE corpus = '{c}'))"""
        )
    return f"""{artifacts(corpora)},
norm AS MATERIALIZED (SELECT *, body <> payload AS had_prefix, runtime <> body AS had_trailer, md5(payload) AS raw_hash, md5(runtime) AS runtime_hash, md5(tok) AS token_hash
  FROM ({" UNION ALL ".join(parts)}))"""


def units(corpora: list[str], stages: tuple[str, ...] = STAGES) -> str:
    """CTEs up to unit."""
    age = f"coalesce(deployed_us, {LATEST}), artifact_id"
    return f"""{normalized(corpora, stages)},
unit AS MATERIALIZED (SELECT corpus, origin, token_hash, first(artifact_id ORDER BY {age}) AS unit_id, count(*) AS n_dup, count(DISTINCT runtime_hash) AS n_runtime,
  count(DISTINCT creator) AS n_creators, first(creator ORDER BY {age}) AS creator, first(deployed_us ORDER BY {age}) AS first_seen_us, min(tok) AS tok, min(length(runtime)) AS n_bytes
  FROM norm GROUP BY corpus, origin, token_hash)"""


def _boundary_pieces(dialect: str, method: str, step: int) -> str:
    ends = {
        "fixed": f"i % {step} = 0",
        "random": "('0x' || substr(md5(unit_id || ':' || (i - 1)::VARCHAR || ':42'), 1, 8))::BIGINT % 8 = 0",
    }[method]
    gap = _GAP.get(dialect, " ")
    marked = f"coalesce(array_to_string(list_transform({token_list(dialect)}, lambda t, i: t || CASE WHEN {ends} THEN '|' ELSE '{gap}' END), ''), '')"
    return f"list_filter(list_transform(string_split({marked}, '|'), lambda p: trim(p, ' ')), lambda p: p <> '')"


def pieces_of(dialect: str, method: str = "block", step: int = 7) -> str:
    return _PIECES[dialect] if method == "block" else _boundary_pieces(dialect, method, step)


def fingers(corpora: list[str], method: str = "block", stages: tuple[str, ...] = STAGES, chars: int = 8, step: int = 7) -> str:
    """CTEs up to finger."""
    parts = []
    for c in corpora:
        d = CORPORA[c]
        parts.append(
            f"""SELECT *, {symbols('pieces', chars)} AS fp, len(pieces) AS fp_len, {_count(d)} AS n_ops, len(pieces) AS n_pieces,
      len(list_distinct({token_list(d)})) AS n_distinct_ops, len(regexp_extract_all(tok, '{_ENDER[d]}')) AS n_terminators,
      greatest(n_bytes - length(tok), 0) AS n_operand_bytes FROM (SELECT *, {pieces_of(d, method, step)} AS pieces FROM unit WHERE corpus = '{c}')"""
        )
    return f"{units(corpora, stages)},\nfinger AS MATERIALIZED ({' UNION ALL '.join(parts)})"


def prune(rule: str | None, threshold: int = 70) -> str:
    if rule in (None, "none"):
        return "true"
    if rule == "length":
        return "10 * least(x.n_ops, y.n_ops) >= 7 * greatest(x.n_ops, y.n_ops)"
    if rule == "attrs":
        return "10 * (" + " + ".join(f"(10 * least(x.{c}, y.{c}) < 7 * greatest(x.{c}, y.{c}))::INT" for c in ATTRIBUTES) + f") <= 3 * {len(ATTRIBUTES)}"
    if rule == "fp_len":
        return f"100 * least(x.fp_len, y.fp_len) >= {threshold} * greatest(x.fp_len, y.fp_len)"
    raise ValueError(rule)


def compared(corpora: list[str], rule: str | None = "length", **kw) -> str:
    """CTEs up to comp: all pairs that the rule keeps, scored."""
    return f"""{fingers(corpora, **kw)},
comp AS MATERIALIZED (SELECT corpus, origin, a, b, la, lb, dist, max_len, (10000 * (max_len - dist)) // max_len AS score_bp FROM (
  SELECT x.corpus, x.origin, x.unit_id AS a, y.unit_id AS b, x.fp_len AS la, y.fp_len AS lb, levenshtein(x.fp, y.fp) AS dist, greatest(x.fp_len, y.fp_len) AS max_len
  FROM finger x JOIN finger y ON x.corpus = y.corpus AND x.origin = y.origin AND x.unit_id < y.unit_id AND {prune(rule)} WHERE x.fp_len > 0 AND y.fp_len > 0))"""


def pairs(corpora: list[str], threshold: int = 70, rule: str | None = "length", strict: bool = False, **kw) -> str:
    """CTEs up to pair."""
    test = f"100 * (max_len - dist) > {threshold} * max_len" if strict else f"100 * (max_len - dist) >= {threshold} * max_len"
    return f"{compared(corpora, rule, **kw)},\npair AS MATERIALIZED (SELECT * FROM comp WHERE {test})"


def components(edges: str = "pair", a: str = "a", b: str = "b", prefix: str = "") -> str:
    """CTEs sym, reach and label (v, l): least member of each component; needs WITH RECURSIVE."""
    return f"""{prefix}sym AS MATERIALIZED (SELECT {a} AS p, {b} AS q FROM {edges} UNION SELECT {b}, {a} FROM {edges}),
{prefix}reach(v, l) AS (SELECT p, p FROM {prefix}sym UNION SELECT s.q, r.l FROM {prefix}reach r JOIN {prefix}sym s ON s.p = r.v AND s.q >= r.l),
{prefix}label AS MATERIALIZED (SELECT v, min(l) AS l FROM {prefix}reach GROUP BY v)"""


def clusters(corpora: list[str], threshold: int = 70, **kw) -> str:
    return f"{pairs(corpora, threshold, **kw)},\n{components()},\ncl AS (SELECT v AS unit_id, l AS cluster_id FROM label)"


def findings() -> str:
    """CTE found over unit of documents: kinds of the representative's payload."""
    by_pattern = " UNION ALL ".join(f"SELECT unit_id, '{k}' AS ftype, len(regexp_extract_all(payload, '{p}')) AS n FROM rep" for k, p in PATTERNS.items())
    return f"""rep AS (SELECT u.unit_id, a.payload FROM unit u JOIN art a ON a.artifact_id = u.unit_id),
found AS MATERIALIZED (SELECT * FROM ({by_pattern}
  UNION ALL SELECT unit_id, 'contamination', count(DISTINCT b.text) FROM rep JOIN benchmark b ON b.text <> '' AND contains(payload, b.text) GROUP BY 1
  UNION ALL SELECT u.unit_id, 'toxic', toxic FROM unit u JOIN labels ON doc_id::VARCHAR = u.unit_id WHERE toxic = 1
  UNION ALL SELECT u.unit_id, 'low_quality', 1 FROM unit u JOIN labels ON doc_id::VARCHAR = u.unit_id WHERE quality = 0) WHERE n > 0)"""


def with_(ctes: str, body: str) -> str:
    return f"WITH RECURSIVE {ctes}\n{body}"
