"""SQL (DuckDB) for those of the queries whose results SQL can state in full."""

from __future__ import annotations

from ..plans.sql import chain
from . import chat, mixing

_BASE32 = "ABCDEFGHIJKLMNOPQRSTUVWXYZ234567"
_ESC = chat.ESCAPE


def warc() -> str:
    quarter = "".join(f"WHEN '{h}' THEN '{i:04b}' " for i, h in enumerate("0123456789abcdef"))
    return f"""
WITH p AS (SELECT page_id, octet_length(encode(coalesce(html, ''))) AS payload_bytes, sha1(coalesce(html, '')) AS h FROM pages),
bits AS (SELECT h, list_aggregate(list_transform(range(1, 41), lambda i: CASE substr(h, i, 1) {quarter} END), 'string_agg', '') AS b FROM (SELECT DISTINCT h FROM p)),
d AS (SELECT h, list_aggregate(list_transform(range(0, 32), lambda i: substr('{_BASE32}', 1 + CAST(
  16 * CAST(substr(b, 5 * i + 1, 1) AS INT) + 8 * CAST(substr(b, 5 * i + 2, 1) AS INT) + 4 * CAST(substr(b, 5 * i + 3, 1) AS INT) + 2 * CAST(substr(b, 5 * i + 4, 1) AS INT) + CAST(substr(b, 5 * i + 5, 1) AS INT) AS INT), 1)), 'string_agg', '') AS digest FROM bits),
f AS (SELECT h, min(page_id) AS first FROM p GROUP BY h)
SELECT page_id, CAST(payload_bytes AS BIGINT) AS payload_bytes, digest AS payload_digest,
  CASE WHEN page_id > first THEN 'revisit' ELSE 'response' END AS record_type,
  CASE WHEN page_id > first THEN first END AS refers_to, TRUE AS verified
FROM p JOIN d USING (h) JOIN f USING (h)"""


def chats() -> str:
    def esc(x: str) -> str:
        out = f"replace({x}, '{_ESC}', '{_ESC}0')"
        for s, c in zip(chat.CONTROL, chat.CODES):
            out = f"replace({out}, '{s}', '{_ESC}{c}')"
        return out

    held = " OR ".join(f"contains({c}, '{s}')" for c in ("role", "text") for s in (_ESC, *chat.CONTROL)) + " OR contains(role, ']')"
    other = f"replace({esc('role')}, ']', '{_ESC}c')"
    return f"""
WITH r AS (SELECT conv_id, turn, coalesce(role, '') AS role, coalesce(text, '') AS text FROM conversations
  UNION ALL SELECT -7, 0, 'user', '</s>[INST] ok [/INST]' UNION ALL SELECT -7, 1, 'assistant', '</s>[INST] ok [/INST]'),
m AS (SELECT *, bool_or({held}) OVER (PARTITION BY conv_id) AS held FROM r),
t AS (SELECT *, CASE WHEN held THEN {esc('text')} ELSE text END AS shown,
  CASE role WHEN 'user' THEN 4 WHEN 'assistant' THEN 3 WHEN 'system' THEN 3 ELSE 4 END AS kind,
  CASE role WHEN 'user' THEN 4 WHEN 'assistant' THEN 3 WHEN 'system' THEN 3 ELSE 5 + length(CASE WHEN held THEN {other} ELSE role END) END AS tag FROM m)
SELECT conv_id, count(*) AS n_turns,
  sha256(string_agg(role || chr(10) || text || chr(10), '' ORDER BY turn NULLS FIRST, role, text)) AS turns_sha256,
  CAST(coalesce(sum(length(text)) FILTER (role = 'assistant'), 0) AS BIGINT) AS loss_chars,
  sha256(coalesce(string_agg(text, '' ORDER BY turn NULLS FIRST, role, text) FILTER (role = 'assistant'), '')) AS loss_sha256,
  CAST(sum(4 + tag + 2 + length(shown) + 3 + kind + 1 + 5) + max(CASE WHEN held THEN {len(chat.HEAD_ESCAPED)} ELSE {len(chat.HEAD_PLAIN)} END) AS BIGINT) AS formatted_chars
FROM t GROUP BY conv_id"""


def similar() -> str:
    """All pairs by their shared runs, and classes by following links: exact, for small tables."""
    return r"""
WITH RECURSIVE w AS (SELECT doc_id, regexp_extract_all(lower(coalesce(text, '')), '[\p{L}\p{N}_]+') AS ws FROM documents),
g AS (SELECT doc_id, unnest(CASE WHEN len(ws) = 0 THEN CAST([] AS VARCHAR[]) WHEN len(ws) < 5 THEN [array_to_string(ws, ' ')]
  ELSE list_distinct(list_transform(range(1, len(ws) - 3), lambda i: array_to_string(ws[i:i + 4], ' '))) END) AS s FROM w),
size AS (SELECT doc_id, count(*) AS n FROM g GROUP BY doc_id),
shared AS (SELECT x.doc_id AS a, y.doc_id AS b, count(*) AS c FROM g x JOIN g y ON x.s = y.s AND x.doc_id <> y.doc_id GROUP BY 1, 2),
link AS (SELECT a, b FROM shared JOIN size x ON x.doc_id = a JOIN size y ON y.doc_id = b WHERE c >= 0.8e0 * (x.n + y.n - c) - 1e-9
  UNION ALL SELECT x.doc_id, y.doc_id FROM w x JOIN w y ON len(x.ws) = 0 AND len(y.ws) = 0 AND x.doc_id <> y.doc_id),
reach AS (SELECT doc_id AS node, doc_id AS root FROM w UNION SELECT link.b, reach.root FROM reach JOIN link ON link.a = reach.node)
SELECT node AS doc_id, min(root) AS class_id, (SELECT count(*) FROM link WHERE a = node) AS n_links FROM reach GROUP BY node"""


def leaks() -> str:
    """Every window of every document scored against every item, without an index."""
    words = r"[\p{L}\p{N}_]+"
    grams = lambda x, n: f"list_distinct(list_transform(range(1, len({x}) - {n} + 2), lambda i: array_to_string({x}[i:i + {n} - 1], ' ')))"
    share = lambda g, n: f"CASE WHEN len({g}) = 0 THEN 1e0 ELSE len(list_intersect({g}, {grams('here', n)})) / len({g}) END"
    return rf"""
WITH it AS (SELECT item_id, text, regexp_extract_all(lower(text), '{words}') AS ws FROM (SELECT DISTINCT item_id, coalesce(text, '') AS text FROM benchmark)),
items AS (SELECT * FROM it WHERE len(ws) > 0),
facts AS (SELECT count(*) AS n, avg(len(ws)) AS mean, max(len(ws)) AS span FROM items),
tf AS (SELECT item_id, w, count(*) AS c FROM (SELECT item_id, unnest(ws) AS w FROM items) GROUP BY ALL),
df AS (SELECT w, count(*) AS df FROM tf GROUP BY w),
impact AS (SELECT item_id, w, ln(1 + (n - df + 0.5e0) / (df + 0.5e0)) * c * 2.2e0 / (c + 1.2e0 * (0.25e0 + 0.75e0 * len(ws) / mean)) AS v FROM tf JOIN df USING (w) JOIN items USING (item_id), facts),
own AS (SELECT item_id, sum(v) AS whole FROM impact GROUP BY item_id),
cut AS (SELECT item_id, list_filter(list_transform(string_split(regexp_replace(text, '([.!?])\s+', '\1' || chr(1), 'g'), chr(1)), lambda s: regexp_extract_all(lower(s), '{words}')), lambda p: len(p) > 0) AS p FROM items),
qa AS (SELECT item_id, CASE WHEN len(p) > 1 THEN flatten(p[1:len(p) - 1]) ELSE p[1][1:len(p[1]) - len(p[1]) // 3] END AS q, CASE WHEN len(p) > 1 THEN p[len(p)] ELSE p[1][len(p[1]) - len(p[1]) // 3 + 1:len(p[1])] END AS a FROM cut),
runs AS (SELECT item_id, least(3, len(q)) AS nq, least(3, len(a)) AS na, CASE WHEN len(q) = 0 THEN [] ELSE {grams('q', 'least(3, len(q))')} END AS gq, CASE WHEN len(a) = 0 THEN [] ELSE {grams('a', 'least(3, len(a))')} END AS ga FROM qa),
d AS (SELECT doc_id, regexp_extract_all(lower(coalesce(text, '')), '{words}') AS ws FROM documents),
lows AS (SELECT doc_id, ws, span, unnest(range(0, greatest(1, len(ws) - span), span)) AS lo FROM d, facts WHERE len(ws) > 0),
win AS (SELECT doc_id, lo, least(len(ws), lo + 2 * span) AS hi, ws[lo + 1:least(len(ws), lo + 2 * span)] AS here FROM lows),
scored AS (SELECT doc_id, lo, item_id, round(sum(v) / any_value(whole), 9) AS score FROM (SELECT DISTINCT doc_id, lo, unnest(here) AS w FROM win) JOIN impact USING (w) JOIN own USING (item_id) GROUP BY ALL),
good AS (SELECT * FROM scored WHERE score >= 0.5e0),
held AS (SELECT doc_id, item_id, score, lo, hi, {share('gq', 'nq')} AS q, {share('ga', 'na')} AS a FROM good JOIN win USING (doc_id, lo) JOIN runs USING (item_id))
SELECT doc_id, item_id, score, q AS question_overlap, a AS answer_overlap, CAST(lo AS INT) AS word_from, CAST(hi AS INT) AS word_to
FROM (SELECT *, row_number() OVER (PARTITION BY doc_id, item_id ORDER BY score DESC, lo) AS r FROM held WHERE q >= 0.5e0 AND a >= 0.5e0) WHERE r = 1"""


def mix(block: int = 128) -> str:
    m = 1 << 31
    dice = lambda x, salt: f"(((xor((((({x}) % {m}) + {m}) % {m} * 1103515245 + ({salt}) * 12345 + 12345) % {m}, ((((({x}) % {m}) + {m}) % {m} * 1103515245 + ({salt}) * 12345 + 12345) % {m}) >> 16)) * 1103515245 + 12345) % {m})"
    rounds: list[dict[str, str]] = []
    for r in range(mixing.ROUNDS):
        rounds.append({"mirror": f"(({dice(f'salt * {mixing.ROUNDS} + {r}', 7)} % blocks) - x + blocks) % blocks"})
        rounds.append({"x": f"CASE WHEN (({dice(f'greatest(x, mirror) * {mixing.ROUNDS} + {r}', 'salt')} >> 20) & 1) = 1 THEN mirror ELSE x END"})
    return rf"""
WITH sized AS (SELECT doc_id, source, CAST(len(regexp_extract_all(coalesce(text, ''), '[^\x20\x09-\x0D]+')) AS BIGINT) AS size FROM documents),
parts AS (SELECT greatest(1, CAST(floor(sqrt(count(*))) AS BIGINT)) AS parts FROM sized),
dealt AS (SELECT *, ({dice('coalesce(doc_id, 0)', 0)} >> 6) % parts AS part FROM sized, parts),
placed AS (SELECT doc_id, source, size, CAST(sum(size) OVER (PARTITION BY source ORDER BY part, doc_id, size ROWS UNBOUNDED PRECEDING) - size AS BIGINT) AS start FROM dealt),
src AS (SELECT source, CAST(sum(size) AS BIGINT) AS source_size, row_number() OVER (ORDER BY source NULLS LAST) AS rank FROM sized GROUP BY source),
capped AS (SELECT *, [3e0, 1e0, 2e0][(rank - 1) % 3 + 1] AS weight, source_size * 2e0 AS cap, sum(source_size) OVER () * 1.5e0 AS total FROM src),
level AS (SELECT *, cap / weight AS ratio, (total - coalesce(sum(cap) OVER (ORDER BY cap / weight, rank ROWS BETWEEN UNBOUNDED PRECEDING AND 1 PRECEDING), 0e0))
  / sum(weight) OVER (ORDER BY cap / weight, rank ROWS BETWEEN CURRENT ROW AND UNBOUNDED FOLLOWING) AS level FROM capped),
open AS (SELECT (SELECT level FROM level WHERE level < ratio ORDER BY ratio, rank LIMIT 1) AS open),
targets AS (SELECT source, source_size, rank, CASE WHEN open IS NULL THEN cap ELSE least(cap, open * weight) END AS target FROM level, open),
want AS (SELECT *, CAST(ceil(source_size / {block}e0) AS BIGINT) AS blocks, target * ceil(source_size / {block}e0) / source_size AS want FROM targets WHERE source_size > 0),
slots AS (SELECT CAST(round_even(sum(want), 0) AS BIGINT) AS slots, greatest(1024, CAST(floor(sqrt(round_even(sum(want), 0))) AS BIGINT)) AS each FROM want),
edges AS (SELECT rank, blocks, CAST(round(sum(want) OVER (ORDER BY rank)) AS BIGINT) AS till, sum(want) OVER (ORDER BY rank) / sum(want) OVER () AS hi, rank = max(rank) OVER () AS final FROM want),
spans AS (SELECT rank, blocks, till - coalesce(lag(till) OVER (ORDER BY rank), 0) AS quota, CASE WHEN final THEN 1e0 ELSE hi END AS hi, coalesce(lag(hi) OVER (ORDER BY rank), 0e0) AS lo FROM edges),
throws AS (SELECT id // each AS shard, id % each AS x FROM (SELECT unnest(range(slots)) AS id, * FROM slots)),
{chain('throws', ['shard', 'x'], [{'u': dice('shard', 3)}, {'u': dice('x', 'u')}, {'u': f"({dice('u', 5)} + 0.5e0) / {m}e0"}], 'thrown')},
counts AS (SELECT rank, shard, count(*) AS c FROM thrown JOIN spans ON u >= lo AND u < hi GROUP BY rank, shard),
totals AS (SELECT rank, blocks, quota, coalesce((SELECT sum(c) FROM counts k WHERE k.rank = spans.rank), 0) AS made FROM spans),
misses AS (SELECT *, greatest(made - quota, 0) AS over, greatest(quota - made, 0) AS under FROM totals),
draw AS (SELECT *, sum(over) OVER (ORDER BY rank) - over AS given, sum(under) OVER (ORDER BY rank) - under AS got FROM misses),
firsts AS (SELECT *, CAST(sum(c) OVER (PARTITION BY rank ORDER BY shard) - c AS BIGINT) AS first FROM counts JOIN draw USING (rank)),
numbered AS (SELECT *, unnest(range(first, first + c)) AS n FROM firsts),
spread AS (SELECT *, floor((n + 0.5e0) * (over / made)) AS before, floor((n + 1.5e0) * (over / made)) AS after FROM numbered),
lacking AS (SELECT rank, blocks, got + k AS j, made + k AS n FROM (SELECT *, unnest(range(CAST(under AS BIGINT))) AS k FROM draw)),
chosen AS (SELECT rank, blocks, CAST(n - before AS BIGINT) AS n FROM spread WHERE after = before
  UNION ALL SELECT l.rank, l.blocks, CAST(l.n AS BIGINT) FROM spread s JOIN lacking l ON l.j = s.given + s.before WHERE s.after > s.before),
drawn AS (SELECT rank, blocks, n % blocks AS x, rank * 16 + n // blocks AS salt FROM chosen WHERE n // blocks < 2),
{chain('drawn', ['rank', 'blocks', 'x', 'salt'], rounds, 'turned')},
pieces AS (SELECT rank, doc_id, size, start, unnest(range(start // {block}, (start + size - 1) // {block} + 1)) AS block FROM placed p JOIN targets t ON p.source IS NOT DISTINCT FROM t.source WHERE size > 0),
taken AS (SELECT q.rank, q.doc_id, q.start, CAST(sum(least((q.block + 1) * {block} - q.start, q.size) - greatest(q.block * {block} - q.start, 0)) AS BIGINT) AS taken
  FROM turned JOIN pieces q ON turned.rank = q.rank AND turned.x = q.block GROUP BY 1, 2, 3)
SELECT p.doc_id, p.size, t.source_size, t.target, coalesce(k.taken, 0) AS taken, p.source
FROM placed p JOIN targets t ON p.source IS NOT DISTINCT FROM t.source LEFT JOIN taken k ON k.rank = t.rank AND k.start = p.start AND k.doc_id = p.doc_id AND p.size > 0"""


ORACLES = {"op2_decontamination": leaks(), "op5_jaccard_join": similar(), "op6_warc": warc(), "op8_mixing": mix(), "op10_chat_format": chats()}
