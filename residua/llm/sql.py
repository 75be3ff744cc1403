"""DuckDB statements for the queries that SQL can express."""

from __future__ import annotations

from .licenses import TEMPLATES
from .secrets import RULES


def quoted(value: str) -> str:
    return "'" + value.replace("'", "''") + "'"


# ---- chat formatting: counts and digests from the given rows, and the length of the template

ESCAPE = r"regexp_replace(replace({c}, '\', '\b'), '<(/?turn\+?>)', '\\l\1', 'g')"

CHAT = rf"""
WITH t AS (
  SELECT conv_id, CAST(turn AS BIGINT) AS turn, coalesce(role, '') AS role, coalesce(text, '') AS text FROM conversations
  UNION ALL SELECT -7, 0, 'user', '\### Assistant: </turn> ok'
  UNION ALL SELECT -7, 1, 'assistant', '\### Assistant: </turn> ok'),
o AS (
  SELECT *, row_number() OVER w AS k, lag(role) OVER w AS before, lead(role) OVER w AS after
  FROM t WINDOW w AS (PARTITION BY conv_id ORDER BY turn NULLS FIRST, role, text)),
p AS (
  SELECT *, length({ESCAPE.format(c='text')})
    + CASE WHEN before = role THEN length('<turn+>') ELSE length('<turn>') + length(replace({ESCAPE.format(c='role')}, chr(10), '\n')) + 1 END
    + CASE WHEN after = role THEN 0 ELSE length('</turn>') + 1 END AS chars
  FROM o)
SELECT conv_id, count(*) AS n_turns,
  sha256(string_agg(role || chr(10) || text || chr(10), '' ORDER BY k)) AS turns_sha256,
  CAST(coalesce(sum(length(text)) FILTER (role = 'assistant'), 0) AS BIGINT) AS loss_chars,
  sha256(coalesce(string_agg(text, '' ORDER BY k) FILTER (role = 'assistant'), '')) AS loss_sha256,
  CAST(sum(chars) AS BIGINT) AS formatted_chars
FROM p GROUP BY conv_id"""

# ---- license scans: bigrams of every line and of texts of several lines against those of the templates

NORMAL = r"regexp_replace(lower({c}), '[^\p{{L}}\p{{N}}\n]+', ' ', 'g')"
WORDS = "[w FOR w IN string_split({c}, ' ') IF w <> '']"
BIGRAMS = "CASE WHEN len(w) = 1 THEN [w[1] || ' '] ELSE [w[i] || ' ' || w[i + 1] FOR i IN range(1, len(w))] END"

LICENSES = f"""
WITH d AS (SELECT row_number() OVER () AS rid, doc_id, {NORMAL.format(c="coalesce(text, '')")} AS body FROM documents),
s AS (SELECT rid, string_split(body, chr(10)) AS parts FROM d),
units AS (
  SELECT rid, generate_subscripts(parts, 1) AS unit, unnest(parts) AS line FROM s
  UNION ALL SELECT rid, 0, replace(body, chr(10), ' ') FROM d WHERE contains(body, chr(10))),
words AS (SELECT rid, unit, {WORDS.format(c='line')} AS w FROM units),
g AS (SELECT DISTINCT rid, unit, unnest({BIGRAMS}) AS gram FROM words WHERE len(w) > 0),
tw AS (SELECT tid, name, {WORDS.format(c=NORMAL.format(c='body'))} AS w FROM (VALUES {', '.join(f'({i}, {quoted(n)}, {quoted(b)})' for i, (n, b) in enumerate(TEMPLATES))}) v(tid, name, body)),
tg AS (SELECT DISTINCT tid, name, unnest({BIGRAMS}) AS gram FROM tw),
ts AS (SELECT tid, count(*) AS m FROM tg GROUP BY tid),
gs AS (SELECT rid, unit, count(*) AS n FROM g GROUP BY rid, unit),
c AS (SELECT rid, unit, tid, name, count(*) AS common FROM g JOIN tg USING (gram) GROUP BY rid, unit, tid, name),
dice AS (SELECT *, CAST(2 * common AS DOUBLE) / (n + m) AS score FROM c JOIN gs USING (rid, unit) JOIN ts USING (tid)),
hit AS (SELECT * FROM dice WHERE score >= 0.8e0 QUALIFY row_number() OVER (PARTITION BY rid, unit ORDER BY score DESC, m, name, tid) = 1),
a AS (
  SELECT rid, string_agg(DISTINCT name, ',' ORDER BY name) AS licenses, count(*) AS n_hits, max(score) AS score,
    string_agg(unit || ':' || name || ':' || format('{{:.6f}}', score), ',' ORDER BY unit) AS hits
  FROM hit GROUP BY rid),
b AS (SELECT rid, name AS best FROM hit QUALIFY row_number() OVER (PARTITION BY rid ORDER BY score DESC, unit) = 1)
SELECT doc_id, coalesce(licenses, '') AS licenses, best, coalesce(score, 0e0) AS score, coalesce(n_hits, 0) AS n_hits, coalesce(hits, '') AS hits
FROM d LEFT JOIN a USING (rid) LEFT JOIN b USING (rid)"""

# ---- embedding near-dedup: all pairs, then closure

NEAR = """
WITH RECURSIVE ok AS (
  SELECT vec_id, CAST(embedding AS DOUBLE[]) AS e FROM embeddings
  WHERE embedding IS NOT NULL AND list_count(embedding) = len(embedding) AND len([x FOR x IN embedding IF NOT isfinite(x)]) = 0 AND len([x FOR x IN embedding IF x <> 0]) > 0),
l AS (SELECT a.vec_id AS a, b.vec_id AS b FROM ok a JOIN ok b ON a.vec_id <> b.vec_id AND len(a.e) = len(b.e) WHERE list_cosine_similarity(a.e, b.e) >= 0.95e0),
r(a, b) AS (SELECT a, b FROM l UNION SELECT r.a, l.b FROM r JOIN l ON r.b = l.a),
n AS (SELECT a, count(*) AS n_links FROM l GROUP BY a),
m AS (SELECT a, min(b) AS least FROM r GROUP BY a)
SELECT v.vec_id, coalesce(n_links, 0) AS n_links, least(v.vec_id, m.least) AS component_id, v.vec_id = least(v.vec_id, m.least) AS kept
FROM embeddings v LEFT JOIN n ON n.a = v.vec_id LEFT JOIN m ON m.a = v.vec_id"""

# ---- curriculum: targets by the level at which sources reach their caps, places by running sums in hash order

AT = "greatest(0e0, least(1e0, CASE WHEN target > 0 THEN CAST({w} AS DOUBLE) / target ELSE 0e0 END))"
TIME = f"least(1e0, 2 * {AT} / ((1 - slope) + sqrt((1 - slope) * (1 - slope) + 4 * slope * {AT})))"

MIX = rf"""
WITH d AS (
  SELECT doc_id, source, CAST(coalesce(len(regexp_extract_all(text, '[^\x20\x09-\x0D]+')), 0) AS BIGINT) AS size,
    CAST('0x' || substr(md5(coalesce(CAST(doc_id AS VARCHAR), '') || ':' || coalesce(text, '')), 1, 15) AS BIGINT) AS h
  FROM documents),
s AS (SELECT source, CAST(sum(size) AS BIGINT) AS source_size FROM d GROUP BY source),
p AS (SELECT *, row_number() OVER (ORDER BY source NULLS LAST) - 1 AS place FROM s),
w AS (SELECT *, CAST([3, 1, 2][place % 3 + 1] AS DOUBLE) AS weight, [0.5e0, -0.5e0, 0e0][place % 3 + 1] AS slope, 2e0 * source_size AS cap FROM p),
q AS (
  SELECT *, (1.5e0 * (SELECT sum(source_size) FROM s) - coalesce(sum(cap) OVER (o ROWS BETWEEN UNBOUNDED PRECEDING AND 1 PRECEDING), 0e0))
    / sum(weight) OVER (o ROWS BETWEEN CURRENT ROW AND UNBOUNDED FOLLOWING) AS level
  FROM w WINDOW o AS (ORDER BY cap / weight, source NULLS LAST)),
f AS (SELECT level FROM q WHERE level * weight <= cap ORDER BY cap / weight, level LIMIT 1),
t AS (SELECT source, source_size, slope, coalesce(least(cap, weight * (SELECT level FROM f)), cap) AS target FROM q),
r AS (
  SELECT doc_id, d.source, size, source_size, slope, target,
    CAST(sum(size) OVER (PARTITION BY d.source ORDER BY h, doc_id, size ROWS BETWEEN UNBOUNDED PRECEDING AND CURRENT ROW) AS BIGINT) - size AS pos
  FROM d JOIN t ON d.source IS NOT DISTINCT FROM t.source),
u AS (SELECT *, CASE WHEN source_size > 0 THEN least(2, CAST(floor(target) AS BIGINT) // source_size) ELSE 0 END AS whole FROM r),
x AS (SELECT *, greatest(0, least(size, greatest(0, CAST(floor(target) AS BIGINT) - whole * source_size) - pos)) AS last FROM u),
y AS (SELECT *, CAST(whole * size + last AS BIGINT) AS taken, CASE WHEN last > 0 THEN whole * source_size + pos + last ELSE (whole - 1) * source_size + pos + size END AS stop FROM x)
SELECT doc_id, size, source_size, target, taken,
  CASE WHEN taken > 0 THEN {TIME.format(w='pos')} END AS position,
  CASE WHEN taken > 0 THEN {TIME.format(w='stop')} END AS last_position
FROM y"""

# ---- secret scans: matches of every rule over every text, places from the lengths between them


def _matches(place: int) -> str:
    rule = RULES[place]
    p = quoted(rule.pattern)
    return (
        f"SELECT rid, {place} AS place, {quoted(rule.kind)} AS kind, {rule.least} AS least, generate_subscripts(hits, 1) AS k, unnest(hits) AS hit, unnest(kept) AS kept, unnest(gaps[:len(hits)]) AS gap "
        f"FROM (SELECT rid, regexp_extract_all(body, {p}) AS hits, regexp_extract_all(body, {p}, {rule.group}) AS kept, string_split_regex(body, {p}) AS gaps FROM d WHERE regexp_matches(body, {p}))"
    )


SECRETS = f"""
WITH d AS (SELECT row_number() OVER () AS rid, doc_id, coalesce(text, '') AS body FROM documents),
m AS ({' UNION ALL '.join(_matches(i) for i in range(len(RULES)))}),
e AS (SELECT *, CAST(sum(length(gap) + length(hit)) OVER (PARTITION BY rid, place ORDER BY k) AS BIGINT) AS stop FROM m),
s AS (SELECT rid, place, kind, stop - length(hit) AS start, kind || ':' || (stop - length(hit)) || ':' || stop AS span FROM e WHERE length(kept) >= least),
a AS (
  SELECT rid, {', '.join(f"count(*) FILTER (kind = {quoted(r.kind)}) AS n_{r.kind}" for r in RULES if r.base)},
    string_agg(span, ',' ORDER BY start, place) FILTER (place IN ({', '.join(str(i) for i, r in enumerate(RULES) if r.base)})) AS base, string_agg(span, ',' ORDER BY start, place) AS spans
  FROM s GROUP BY rid)
SELECT doc_id, {', '.join(f"coalesce(n_{r.kind}, 0) AS n_{r.kind}" for r in RULES if r.base)}, sha256(coalesce(base, '')) AS base_sha256, coalesce(spans, '') AS spans
FROM d LEFT JOIN a USING (rid)"""

ORACLES: dict[str, str] = {
    "op2_chat_format": CHAT,
    "op3_license_scan": LICENSES,
    "op8_embedding_neardup": NEAR,
    "op9_curriculum_mix": MIX,
    "op10_secret_scan": SECRETS,
}
