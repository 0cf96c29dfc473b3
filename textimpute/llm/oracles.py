"""DuckDB SQL for the queries of this subpackage that SQL can express: op1, op4, op6, op9.

The others have none: op2, op5 and op8 are fitted models, op3 is a search over tokenizer output, op7 an index with votes,
op10 needs XXH64 and an iteration; tests hold them against brute-force versions.
"""

from __future__ import annotations

from .queries import INJECTION
from .urlfilter import RULES

LOWER = "translate({x}, 'ABCDEFGHIJKLMNOPQRSTUVWXYZ', 'abcdefghijklmnopqrstuvwxyz')"
_escaped = lambda x: f"replace(replace({x}, '\\', '\\\\'), '<|', '<\\|')"

CHAT = f"""WITH t AS (
 SELECT conv_id::BIGINT AS conv_id, turn, coalesce(role,'') AS role, coalesce(text,'') AS text FROM conversations
 UNION ALL SELECT -1, 0, 'user', '{INJECTION}' UNION ALL SELECT -1, 1, 'assistant', '{INJECTION}'),
o AS (SELECT *, row_number() OVER w AS rn, count(*) OVER (PARTITION BY conv_id) AS n,
 24 + length(replace({_escaped('role')}, chr(10), '\\n')) + length({_escaped('text')}) AS size FROM t WINDOW w AS (PARTITION BY conv_id ORDER BY turn NULLS FIRST, role, text)),
c AS (SELECT *, sum(size) OVER (PARTITION BY conv_id ORDER BY rn ROWS UNBOUNDED PRECEDING) AS upto FROM o)
SELECT conv_id, count(*) AS n_turns, sha256(string_agg(role||chr(10)||text||chr(10), '' ORDER BY rn)) AS turns_sha256,
 length(coalesce(string_agg(text, '' ORDER BY rn) FILTER (role='assistant'), '')) AS loss_chars,
 sha256(coalesce(string_agg(text, '' ORDER BY rn) FILTER (role='assistant'), '')) AS loss_sha256,
 (sum(upto) FILTER (role='assistant' OR rn=n))::BIGINT AS formatted_chars FROM c GROUP BY conv_id"""

WARC = """WITH p AS (SELECT page_id, strlen(coalesce(html,'')) AS payload_bytes, sha1(coalesce(html,'')) AS payload_digest FROM pages),
g AS (SELECT *, CASE WHEN payload_bytes >= 1000 AND count(*) OVER d > 1 THEN max(page_id) OVER d END AS keeper FROM p WINDOW d AS (PARTITION BY payload_digest, payload_bytes))
SELECT page_id, payload_bytes, payload_digest, CASE WHEN keeper IS NULL OR keeper IS NOT DISTINCT FROM page_id THEN 'response' ELSE 'revisit' END AS record_type,
 CASE WHEN keeper IS DISTINCT FROM page_id THEN keeper END AS refers_to FROM g"""

_words = lambda x: f"regexp_extract_all({LOWER.format(x=x)}, '[^\\x00-\\x2F\\x3A-\\x60\\x7B-\\x7F]+')"
DECONTAM = f"""WITH i AS (SELECT item_id, {_words("coalesce(text,'')")} AS w FROM benchmark),
windows AS (SELECT DISTINCT item_id, least(len(w),10) AS size, array_to_string(w[s.i:s.i+least(len(w),10)-1], ' ') AS words FROM i, range(1, greatest(len(w)-9,1)+1) s(i) WHERE len(w) > 0),
d AS (SELECT doc_id, {_words("coalesce(text,'')")} AS w FROM documents),
spots AS (SELECT doc_id, s.i AS start, size, array_to_string(w[s.i:s.i+size-1], ' ') AS words FROM d, (SELECT DISTINCT size FROM windows), range(1, len(w)-size+2) s(i)),
hits AS (SELECT spots.doc_id, start, size, item_id FROM spots JOIN windows USING (size, words)),
places AS (SELECT doc_id, count(DISTINCT start+k.i) AS n_hit FROM hits, range(0, size) k(i) GROUP BY 1),
items AS (SELECT doc_id, count(DISTINCT item_id) AS n_items, string_agg(DISTINCT item_id::VARCHAR, ',' ORDER BY item_id::VARCHAR) AS ids FROM hits GROUP BY 1)
SELECT d.doc_id, len(w) AS n_words, coalesce(n_hit,0) AS n_hit, coalesce(n_items,0) AS n_items, sha256(coalesce(ids,'')) AS items_sha256, coalesce(n_hit,0) > 0 AS contaminated
FROM d LEFT JOIN places USING (doc_id) LEFT JOIN items USING (doc_id)"""

_rules = sorted(RULES, key=lambda r: (-len(r[1]) - len(r[2]), r[0] != "allow", r[1:]))
_fits = lambda h, p: f"(host='{h}' OR ends_with(host, '.{h}')) AND starts_with(path, '{p}')"
#: Without links between the pages (the given tables have none) every page that no rule reaches is allowed.
URLS = f"""WITH r AS (SELECT page_id, CASE WHEN position('://' IN url) > 0 THEN substr(url, position('://' IN url)+3) ELSE '' END AS rest FROM pages),
s AS (SELECT page_id, {LOWER.format(x="regexp_extract(coalesce(rest,''), '^([^/?#]*)', 1)")} AS host, regexp_extract(regexp_replace(coalesce(rest,''), '^[^/?#]*', ''), '(?s)^([^?#]*)', 1) AS path FROM r)
SELECT page_id, host, path, CASE {' '.join(f"WHEN {_fits(h, p)} THEN '{h + p}'" for _, h, p in _rules)} END AS rule,
 CASE {' '.join(f"WHEN {_fits(h, p)} THEN '{a}'" for a, h, p in _rules)} ELSE 'allow' END AS verdict FROM s"""

ORACLES: dict[str, str] = {
    "op1_chat_prefix_targets": CHAT,
    "op4_warc_splittable": WARC,
    "op6_benchmark_suffix_automaton": DECONTAM,
    "op9_url_redirect_equivalence": URLS,
}
