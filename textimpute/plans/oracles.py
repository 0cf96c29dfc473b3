"""DuckDB SQL with the same results as the queries of this package that SQL can express."""

from __future__ import annotations

ORACLES: dict[str, str] = {}


def h(x: str, *salts: str) -> str:
    text = "||'|'||".join([f"({x})::VARCHAR", *(f"'{s}'" for s in salts)])
    return f"(('0x'||substr(md5({text}),1,8))::BIGINT)"


def phone(key: str, nation: str) -> str:
    """Phone number expression; the hash is written out where it is used."""
    v = h(key, "phone")
    code, p3, p4 = f"(200+31*{nation})::VARCHAR", f"lpad(({v}%1000)::VARCHAR,3,'0')", f"lpad((({v}//1000)%10000)::VARCHAR,4,'0')"
    return (f"CASE ({v}//10000000)%4 WHEN 0 THEN {code}||'-'||{p3}||'-'||{p4} WHEN 1 THEN '('||{code}||'-) '||{p3}||' '||{p4} "
            f"WHEN 2 THEN {code}||'/'||{p3}||'-'||{p4} ELSE '+1'||{code}||' '||{p3}||{p4} END")


GEO = f"""geo AS (SELECT c_custkey, n_name, {phone('c_custkey', 'c_nationkey')} AS c_phone,
 'Rated '||(1+{h('c_custkey', 'phone')}%5)||'.0: '||coalesce(substr(doc.text,1,120),'') AS c_reviews, c_name, r_name, c_mktsegment,
 cast(cast(round(c_acctbal,2) AS decimal(18,2)) AS varchar) AS c_acctbal
 FROM customer JOIN nation ON c_nationkey=n_nationkey JOIN region ON n_regionkey=r_regionkey
 CROSS JOIN (SELECT count(*) AS n_docs FROM documents) LEFT JOIN documents doc ON c_custkey % n_docs = doc.doc_id)"""


def masked(condition: str, table: str = "geo", target: str = "n_name", name: str = "masked") -> str:
    """A copy of the table with the target emptied where the condition holds, the truth kept."""
    return f"{name} AS (SELECT * REPLACE (CASE WHEN {condition} THEN NULL ELSE {target} END AS {target}), {target} AS truth, coalesce({condition}, false) AS is_masked FROM {table})"


def mcar(percent: int, key: str = "c_custkey", seed: str = "1") -> str:
    return f"{h(key, seed)} % 100 < {percent}"


MASKED = f"{GEO}, {masked(mcar(10))}"
SUPPLY = f"""sup AS (SELECT s_suppkey, n_name, {phone('s_suppkey', 's_nationkey')} AS s_phone, s_name FROM supplier JOIN nation ON s_nationkey=n_nationkey),
{masked(mcar(10, 's_suppkey'), 'sup')}, queries AS (SELECT * FROM masked WHERE n_name IS NULL), pool AS (SELECT * FROM masked WHERE n_name IS NOT NULL)"""


def oracle(name: str, sql: str) -> None:
    ORACLES[name] = sql


# ------------------------------------------------------------------ set-up
oracle("split_missing", f"WITH {MASKED} SELECT CASE WHEN n_name IS NULL THEN 'query' ELSE 'pool' END AS part, count(*) AS rows FROM masked GROUP BY 1")
for _rate in (10, 20, 30, 40, 50):
    oracle(f"mask_mcar_{_rate}", f"WITH {GEO}, {masked(mcar(_rate))} SELECT c_custkey, n_name, is_masked FROM masked")
_x = h("c_custkey", "1") + " % 100"
oracle("mask_mar", f"WITH {GEO}, {masked(f'({_x} < CASE WHEN c_mktsegment=$$BUILDING$$ THEN 30 ELSE 5 END)')} SELECT c_custkey, n_name, is_masked FROM masked")
oracle("mask_mnar", f"WITH {GEO}, {masked(f'({_x} < CASE WHEN n_name IN ($$NATION_1$$,$$NATION_2$$) THEN 50 ELSE 5 END)')} SELECT c_custkey, n_name, is_masked FROM masked")
oracle("mask_by_group", f"WITH {GEO}, {masked(mcar(40, 'c_mktsegment'))} SELECT c_custkey, n_name, is_masked FROM masked")
_cell = lambda c, key="c_custkey", pct=20: f"CASE WHEN {h(key, '1', c)} % 100 >= {pct} THEN {c} END AS {c}"
oracle("mask_candidates", f"WITH {GEO} SELECT c_custkey, {_cell('c_phone')}, {_cell('c_name')} FROM geo")
oracle("assumption_profile", f"""WITH {MASKED}, per AS (SELECT n_name, count(*) AS n FROM masked WHERE n_name IS NOT NULL GROUP BY 1)
SELECT (SELECT count(*) FROM masked) AS all_rows, (SELECT count(*) FROM masked WHERE n_name IS NULL) AS missing_rows,
(SELECT round(avg(CASE WHEN {h('c_custkey', '1', 'c_phone')} % 100 < 20 THEN 1.0 ELSE 0.0 END),6) FROM masked) AS null_c_phone, 0.0::DOUBLE AS null_c_name,
count(*) AS distinct_values, sum(n)::BIGINT AS complete_rows, round(avg((n>=2)::INT::DOUBLE),6) AS repeated_share FROM per""")


# ------------------------------------------------------------------ sampling
def group_sample(table: str, key: str, target: str, m: int, n: int, seed: str = "1", out: str = "sample") -> str:
    """CTEs of the stratified sample: quota by a recursion over sizes, groups and rows by hash rank."""
    return f"""sizes AS (SELECT {target} AS g, least(count(*),{n}) AS size FROM {table} WHERE {target} IS NOT NULL GROUP BY 1),
hist AS (SELECT size, count(*) AS groups, row_number() OVER (ORDER BY size DESC) AS step FROM sizes GROUP BY size),
quota AS (WITH RECURSIVE walk(step, size, take, budget) AS (
 SELECT 0::BIGINT, 0::BIGINT, 0::BIGINT, {m * n}::BIGINT
 UNION ALL SELECT hist.step, hist.size, least(hist.groups, walk.budget // hist.size), walk.budget - hist.size * least(hist.groups, walk.budget // hist.size)
 FROM walk JOIN hist ON hist.step = walk.step + 1) SELECT size, take FROM walk WHERE step > 0),
chosen AS (SELECT g FROM (SELECT g, size, row_number() OVER (PARTITION BY size ORDER BY {h('g', seed)}, g) AS place FROM sizes) JOIN quota USING (size) WHERE place <= take),
{out} AS (SELECT * EXCLUDE (place) FROM (SELECT *, row_number() OVER (PARTITION BY {target} ORDER BY {h(key, seed)}, {key}) AS place FROM {table} WHERE {target} IN (SELECT g FROM chosen)) WHERE place <= {n})"""


oracle("group_sizes", f"WITH {MASKED} SELECT n_name, count(*) AS group_rows FROM masked WHERE n_name IS NOT NULL GROUP BY 1")
oracle("group_sample_full", f"WITH {GEO}, {group_sample('geo', 'c_custkey', 'n_name', 5, 10)} SELECT c_custkey, n_name FROM sample")
oracle("group_sample_shortfall", f"WITH {GEO}, {group_sample('geo', 'c_custkey', 'n_name', 4, 65)} SELECT c_custkey, n_name FROM sample")
_uniform = lambda n: f"(SELECT * FROM geo ORDER BY {h('c_custkey', '1')}, c_custkey LIMIT {n})"
oracle("uniform_sample", f"WITH {GEO} SELECT c_custkey, n_name FROM {_uniform(100)}")
oracle("sample_coverage", f"""WITH {GEO}, {group_sample('geo', 'c_custkey', 'n_name', 20, 3)},
both_ AS (SELECT 'groups' AS method, count(*) AS sample_rows, count(DISTINCT n_name) AS sample_values FROM sample
 UNION ALL SELECT 'rows', count(*), count(DISTINCT n_name) FROM {_uniform(60)})
SELECT sample_rows, sample_values, t.table_values, round(sample_values / t.table_values, 6) AS covered, method FROM both_ CROSS JOIN (SELECT count(DISTINCT n_name) AS table_values FROM geo) t""")


# ------------------------------------------------------------------ patterns and dependencies
def long_form(table: str, key: str, target: str, attributes: list[str]) -> str:
    parts = [f"SELECT '{a}' AS attribute, {target} AS target_value, ({key})::VARCHAR AS row_id, {a} AS value FROM {table} WHERE {target} IS NOT NULL" for a in attributes]
    return "long_ AS (" + " UNION ALL ".join(parts) + ")"


def mined(q: float) -> str:
    """CTEs grams, freq (all frequent substrings), uniq (frequent in one group only)."""
    return f"""sizes_ AS (SELECT attribute, target_value, count(*) AS group_rows FROM long_ GROUP BY 1,2),
grams AS (SELECT DISTINCT attribute, target_value, row_id, substr(value, s.i, l.n) AS pattern FROM long_, range(1, length(value)+1) s(i), range(1, length(value)-s.i+2) l(n)),
freq AS (SELECT attribute, target_value, pattern, count(*) AS support, group_rows FROM grams JOIN sizes_ USING (attribute, target_value) GROUP BY ALL HAVING count(*) >= {q}::DOUBLE * group_rows),
uniq AS (SELECT * FROM freq WHERE (attribute, pattern) IN (SELECT (attribute, pattern) FROM freq GROUP BY attribute, pattern HAVING count(*) = 1)),
maxi AS (SELECT * FROM uniq u WHERE NOT EXISTS (SELECT 1 FROM uniq o WHERE o.attribute=u.attribute AND o.target_value=u.target_value AND length(o.pattern)>length(u.pattern) AND contains(o.pattern,u.pattern)))"""


def verdict(p: float, table: str = "long_") -> str:
    return f"""SELECT g.attribute, coalesce(c.covered,0)::BIGINT AS covered, g.groups, round(coalesce(c.covered,0)/g.groups,6) AS fraction, coalesce(c.covered,0)/g.groups >= {p} AS holds
FROM (SELECT attribute, count(DISTINCT target_value) AS groups FROM {table} GROUP BY 1) g LEFT JOIN (SELECT attribute, count(DISTINCT target_value) AS covered FROM uniq GROUP BY 1) c USING (attribute)"""


def fractions(ctes: str, table: str, key: str, target: str, attributes: list[str], p: float = 0.75, q: float = 0.75) -> str:
    return f"WITH {ctes}{', ' if ctes else ''}{long_form(table, key, target, attributes)}, {mined(q)} {verdict(p)}"


NATION = """nat AS (SELECT n_nationkey AS id, n_nationkey::VARCHAR AS n_nationkey, n_regionkey::VARCHAR AS n_regionkey, n_name, r_name FROM nation JOIN region ON n_regionkey = r_regionkey)"""
oracle("nation_patterns", f"WITH {NATION}, {long_form('nat', 'id', 'n_name', ['n_nationkey'])}, {mined(0.75)} SELECT * FROM maxi")
oracle("nation_dependency", fractions(NATION, "nat", "id", "n_name", ["n_nationkey", "r_name"]))
oracle("nation_key_dependency", fractions(NATION, "nat", "id", "n_nationkey", ["n_name"]))
oracle("region_dependency", fractions(NATION, "nat", "id", "r_name", ["n_regionkey", "n_name"]))
PHONE = f"WITH {GEO}, {long_form('geo', 'c_custkey', 'n_name', ['c_phone'])}"
oracle("phone_frequent", f"{PHONE}, {mined(0.75)} SELECT * FROM freq")
ORACLES["phone_frequent_native"] = ORACLES["phone_frequent"]
oracle("phone_unique", f"{PHONE}, {mined(0.75)} SELECT * FROM uniq")
oracle("phone_maximal", f"{PHONE}, {mined(0.75)} SELECT * FROM maxi")
oracle("phone_longest", f"""{PHONE}, {mined(0.25)} SELECT attribute, target_value, pattern, support, group_rows FROM freq f
WHERE length(pattern) = (SELECT max(length(pattern)) FROM freq o WHERE o.attribute=f.attribute AND o.target_value=f.target_value)""")
_alone = lambda freq, q: f"(SELECT count(*) FROM (SELECT l.target_value, count(*) AS n, z.group_rows FROM long_ l JOIN sizes_ z USING (attribute, target_value) WHERE l.attribute={freq}.attribute AND contains(l.value, {freq}.pattern) GROUP BY ALL HAVING count(*) >= {q}::DOUBLE * z.group_rows)) = 1"
_longest = f"""{PHONE}, {mined(0.25)}, lon AS (SELECT attribute, target_value, pattern, support, group_rows FROM freq f
WHERE length(pattern) = (SELECT max(length(pattern)) FROM freq o WHERE o.attribute=f.attribute AND o.target_value=f.target_value))"""
oracle("phone_longest_unique", f"{_longest} SELECT * FROM lon WHERE (attribute, pattern) IN (SELECT (attribute, pattern) FROM freq GROUP BY attribute, pattern HAVING count(*) = 1)")
oracle("phone_short_unique", f"{PHONE}, {mined(0.75)} SELECT * FROM uniq WHERE length(pattern) <= 3")
_pairwise = f"""WITH {SUPPLY}, {long_form('sup', 's_suppkey', 'n_name', ['s_phone'])}, sizes_ AS (SELECT attribute, target_value, count(*) AS group_rows FROM long_ GROUP BY 1,2),
two AS (SELECT a.attribute, a.target_value, a.value AS x, b.value AS y FROM long_ a JOIN long_ b ON a.attribute=b.attribute AND a.target_value=b.target_value AND a.row_id > b.row_id),
parts AS (SELECT attribute, target_value, x, y, s.i AS i, l.n AS n, substr(x, s.i, l.n) AS c FROM two, range(1, length(x)+1) s(i), range(1, length(x)-s.i+2) l(n) WHERE contains(y, substr(x, s.i, l.n))),
best AS (SELECT DISTINCT attribute, target_value, c AS pattern FROM (SELECT * FROM parts QUALIFY row_number() OVER (PARTITION BY attribute, target_value, x, y ORDER BY n DESC, i) = 1)),
pair AS (SELECT attribute, target_value, pattern, (SELECT count(*) FROM long_ l WHERE l.attribute=best.attribute AND l.target_value=best.target_value AND contains(l.value, best.pattern)) AS support, group_rows FROM best JOIN sizes_ USING (attribute, target_value)),
pairwise_ AS (SELECT * FROM pair WHERE support >= 0.75::DOUBLE * group_rows)"""
oracle("phone_pairwise", f"{_pairwise} SELECT * FROM pairwise_")
oracle("phone_pairwise_unique", f"{_pairwise} SELECT * FROM pairwise_ WHERE {_alone('pairwise_', 0.75)}")
oracle("phone_all_rows", f"{PHONE}, {mined(1.0)} SELECT * FROM freq")
oracle("phone_recheck_full", f"""{PHONE}, {mined(0.75)}, sizes2 AS (SELECT n_name AS g, count(*) AS group_rows FROM geo GROUP BY 1)
SELECT m.attribute, m.target_value AS of_value, m.pattern, l.target_value, count(*) AS support, s.group_rows, count(*) >= 0.75::DOUBLE * s.group_rows AS frequent
FROM maxi m JOIN long_ l ON m.attribute=l.attribute AND contains(l.value, m.pattern) JOIN sizes2 s ON s.g = l.target_value GROUP BY m.attribute, m.target_value, m.pattern, l.target_value, s.group_rows""")
SHORT = ["c_phone", "c_name", "c_mktsegment", "c_acctbal", "r_name"]
oracle("geo_dependency", fractions(GEO, "geo", "c_custkey", "n_name", SHORT))
oracle("geo_dependency_sampled", fractions(f"{GEO}, {group_sample('geo', 'c_custkey', 'n_name', 10, 10)}", "sample", "c_custkey", "n_name", SHORT))
oracle("geo_region_dependency", fractions(GEO, "geo", "c_custkey", "r_name", ["c_phone"]))
PAGES = r"""pag AS (SELECT page_id, url, regexp_extract(url, '://[^/]+/([a-z]{2})/', 1) AS lang, regexp_extract(url, '://([^/?#]+)', 1) AS host,
 regexp_extract(regexp_extract(url, '://([^/?#]+)', 1), '\.([a-z]+)$', 1) AS tld FROM pages)"""
oracle("pages_url_dependency", fractions(PAGES, "pag", "page_id", "lang", ["url", "host", "tld"]))
oracle("pages_host_selection", fractions(f"{PAGES}, {group_sample('pag', 'page_id', 'host', 10, 10)}", "sample", "page_id", "host", ["url", "tld", "lang"]))
TITLES = """tit AS (SELECT p_partkey, p_brand, CASE p_partkey % 3 WHEN 0 THEN p_brand||' '||p_name||' '||p_type WHEN 1 THEN p_name||' by '||p_brand||', '||p_type
 ELSE p_type||' '||p_name||' ('||p_brand||')' END AS p_title, p_name, p_type, p_size::VARCHAR AS p_size, cast(cast(round(p_retailprice,2) AS decimal(18,2)) AS varchar) AS p_retailprice FROM part)"""
oracle("part_selection", fractions(f"{TITLES}, {group_sample('tit', 'p_partkey', 'p_brand', 10, 10)}", "sample", "p_partkey", "p_brand", ["p_title", "p_name", "p_type", "p_size", "p_retailprice"]))
oracle("geo_selection", fractions(f"{GEO}, {group_sample('geo', 'c_custkey', 'n_name', 10, 10)}", "sample", "c_custkey", "n_name", [*SHORT, "c_reviews"]).replace(" AS holds", " AS holds, coalesce(c.covered,0)/g.groups >= 0.75 AS kept"))
TURNS = "tur AS (SELECT conv_id * 1000 + turn AS id, role, text, turn::VARCHAR AS turn FROM conversations)"
oracle("conversation_role_selection", fractions(f"{TURNS}, {group_sample('tur', 'id', 'role', 10, 10)}", "sample", "id", "role", ["text", "turn"]))
_money = lambda c: f"cast(cast(round({c},2) AS decimal(18,2)) AS varchar) AS {c}"
_stamp = lambda c: f"strftime({c}, '%Y-%m-%d %H:%M:%S') AS {c}"
WIDE = f"""{GEO}, wide AS (SELECT concat_ws('-', l_orderkey, l_linenumber, l_partkey, l_suppkey) AS row_id, n_name, c_phone, c_reviews, c_name, c_mktsegment, c_acctbal, o_orderstatus, o_orderpriority,
 {_money('o_totalprice')}, {_stamp('o_orderdate')}, {_money('l_quantity')}, l_returnflag, {_stamp('l_shipdate')}, p_name, p_brand, p_type, s_name
 FROM lineitem JOIN orders ON l_orderkey=o_orderkey JOIN geo ON o_custkey=c_custkey JOIN part ON l_partkey=p_partkey JOIN supplier ON l_suppkey=s_suppkey)"""
WIDE_COLUMNS = ["c_phone", "c_reviews", "c_name", "c_mktsegment", "c_acctbal", "o_orderstatus", "o_orderpriority", "o_totalprice",
                "o_orderdate", "l_quantity", "l_returnflag", "l_shipdate", "p_name", "p_brand", "p_type", "s_name"]
oracle("wide_orders_selection", fractions(f"{WIDE}, {group_sample('wide', 'row_id', 'n_name', 10, 10)}", "sample", "row_id", "n_name", WIDE_COLUMNS))
MOBILE = f"{TITLES}, mob AS (SELECT concat_ws('-', l_orderkey, l_linenumber, l_partkey, l_suppkey) AS row_id, p_brand, p_title, p_name, p_type, p_size, {_money('l_quantity')} FROM lineitem JOIN tit ON l_partkey = p_partkey)"
oracle("mobile_selection", fractions(f"{MOBILE}, {group_sample('mob', 'row_id', 'p_brand', 10, 10)}", "sample", "row_id", "p_brand", ["p_title", "p_name", "p_type", "p_size", "l_quantity"]))
oracle("part_dependency_negative", fractions(TITLES, "tit", "p_partkey", "p_brand", ["p_type", "p_size"]))
oracle("events_dependency_negative", fractions("eve AS (SELECT event_id, event_type, props, user_id::VARCHAR AS user_id FROM events)", "eve", "event_id", "event_type", ["props", "user_id"]))
_grid = [f"g{i} AS ({verdict(0.5).replace('uniq', f'uniq{i}')})" for i in range(3)]
_freq = ", ".join(f"""freq{i} AS (SELECT attribute, target_value, pattern FROM counts WHERE support >= {q}::DOUBLE * group_rows),
uniq{i} AS (SELECT * FROM freq{i} WHERE (attribute, pattern) IN (SELECT (attribute, pattern) FROM freq{i} GROUP BY attribute, pattern HAVING count(*) = 1))""" for i, q in enumerate((0.25, 0.5, 0.75)))
_cells = " UNION ALL ".join(f"SELECT {p}::DOUBLE AS p, {q}::DOUBLE AS q, count(*) FILTER (covered/groups >= {p}) AS kept FROM g{i}" for i, q in enumerate((0.25, 0.5, 0.75)) for p in (0.25, 0.5, 0.75))
_zero = lambda n: " UNION ALL ".join(f"SELECT {p}::DOUBLE, {q}::DOUBLE, {n}" for p, q in [(0, 0), (0, 0.25), (0, 0.5), (0, 0.75), (0.25, 0), (0.5, 0), (0.75, 0)])


def grid(table: str, key: str, columns: list[str]) -> str:
    """CTEs and rows (p, q, kept) of the grid."""
    return f"""{long_form(table, key, 'n_name', columns)}, {mined(0.75).split('freq AS')[0]}
counts AS (SELECT attribute, target_value, pattern, count(*) AS support, group_rows FROM grams JOIN sizes_ USING (attribute, target_value) GROUP BY ALL), {_freq}, {', '.join(_grid)} {_cells} UNION ALL {_zero(len(columns))}"""


oracle("pq_grid_attribute_counts", f"WITH {GEO}, {grid('geo', 'c_custkey', SHORT)}")
_five = " UNION ALL ".join(f"(WITH {group_sample('wide', 'row_id', 'n_name', 10, 10, str(x))}, {grid('sample', 'row_id', WIDE_COLUMNS)})" for x in range(1, 6))
oracle("wide_pq_grid", f"WITH {WIDE}, runs AS ({_five}) SELECT p, " + ", ".join(f"round(avg(kept) FILTER (q = {x / 100}), 6) AS q_{x}" for x in (0, 25, 50, 75)) + " FROM runs GROUP BY p")
_fd = lambda a: f"SELECT count(*) AS values, count(*) FILTER (n > 1) AS violating_values, max(n) <= 1 AS holds, '{a}' AS attribute FROM (SELECT {a}, count(DISTINCT n_name) AS n FROM geo GROUP BY 1)"
oracle("fd_strict", f"WITH {GEO} {_fd('c_phone')} UNION ALL {_fd('c_mktsegment')}")
_fv = lambda a: f"SELECT sum(r)::BIGINT AS rows, round(1 - sum(k)/sum(r), 6) AS violation_rate, '{a}' AS attribute FROM (SELECT {a}, sum(n) AS r, max(n) AS k FROM (SELECT {a}, p_brand, count(*) AS n FROM part GROUP BY 1,2) GROUP BY 1)"
oracle("fd_violation", f"{_fv('p_name')} UNION ALL {_fv('p_type')}")


# ------------------------------------------------------------------ similarity and retrieval
def lcs(a: str, b: str) -> str:
    return f"coalesce((SELECT max(l.n) FROM range(1, length({a})+1) l(n), range(1, length({a})+1) s(i) WHERE s.i + l.n - 1 <= length({a}) AND contains({b}, substr({a}, s.i, l.n))), 0)"


def similar(pairs: list[tuple[str, str]]) -> str:
    cells = "+".join(f"coalesce(CASE WHEN greatest(length({a}),length({b}))>0 AND {a} IS NOT NULL AND {b} IS NOT NULL THEN {lcs(a, b)}::DOUBLE/greatest(length({a}),length({b})) END, 0)" for a, b in pairs)
    return f"round((0.0+{cells})/{len(pairs)}, 9)"


_pairs = "FROM (SELECT n_name FROM nation) CROSS JOIN (SELECT s_name FROM supplier)"
oracle("lcs_lengths", f"SELECT n_name, s_name, {lcs('n_name', 's_name')}::INT AS lcs {_pairs}")
ORACLES["lcs_lengths_arrow"] = ORACLES["lcs_lengths"]
oracle("lcs_strings", f"""SELECT n_name, s_name, coalesce((SELECT substr(n_name, s.i, l.n) FROM range(1, length(n_name)+1) l(n), range(1, length(n_name)+1) s(i)
 WHERE s.i + l.n - 1 <= length(n_name) AND contains(s_name, substr(n_name, s.i, l.n)) ORDER BY l.n DESC, s.i LIMIT 1), '') AS common {_pairs}""")
SIM2 = similar([("q.s_name", "p.s_name"), ("q.s_phone", "p.s_phone")])
_ratio = lambda c: f"least(length(q.{c}),length(p.{c}))/greatest(length(q.{c}),length(p.{c}))"
oracle("similarity_pairs", f"WITH {SUPPLY} SELECT q.s_name AS q_name, p.s_name AS p_name, {SIM2} AS similarity, round((0.0+{_ratio('s_name')}+{_ratio('s_phone')})/2, 9) AS bound FROM queries q CROSS JOIN pool p")


def topk(k: int, sim: str = similar([("q.s_phone", "p.s_phone")]), diverse: bool = True, setup: str = SUPPLY) -> str:
    """CTE ex: the examples of each query."""
    best = "best AS (SELECT * FROM scored QUALIFY row_number() OVER (PARTITION BY query_id, target_value ORDER BY similarity DESC, example_id) = 1)" if diverse else "best AS (SELECT * FROM scored)"
    return f"""{setup}, scored AS (SELECT q.s_suppkey AS query_id, p.s_suppkey AS example_id, p.n_name AS target_value, {sim} AS similarity FROM queries q CROSS JOIN pool p),
{best}, ex AS (SELECT query_id, (row_number() OVER (PARTITION BY query_id ORDER BY similarity DESC, example_id))::INT AS rank, example_id, target_value, similarity FROM best QUALIFY rank <= {k})"""


for _k in (1, 2, 3, 10):
    oracle(f"topk_diverse_k{_k}", f"WITH {topk(_k)} SELECT * FROM ex")
oracle("topk_plain_k3", f"WITH {topk(3, diverse=False)} SELECT * FROM ex")
ORACLES["topk_indexed_k3"] = ORACLES["topk_diverse_k3"]
ORACLES["topk_blocks_k3"] = ORACLES["topk_diverse_k3"]
_ONE = similar([("q.s_phone", "p.s_phone")])
REGION = f"""reg AS (SELECT s_suppkey, r_name AS n_name, {phone('s_suppkey', 's_nationkey')} AS s_phone, s_name FROM supplier JOIN nation ON s_nationkey=n_nationkey JOIN region ON n_regionkey=r_regionkey),
{masked(mcar(10, 's_suppkey'), 'reg')}, queries AS (SELECT * FROM masked WHERE n_name IS NULL), pool AS (SELECT * FROM masked WHERE n_name IS NOT NULL)"""
oracle("topk_backfill_k10", f"""WITH {REGION}, scored AS (SELECT q.s_suppkey AS query_id, p.s_suppkey AS example_id, p.n_name AS target_value, {_ONE} AS similarity FROM queries q CROSS JOIN pool p),
best AS (SELECT *, row_number() OVER (PARTITION BY query_id, target_value ORDER BY similarity DESC, example_id) > 1 AS again FROM scored)
SELECT query_id, (row_number() OVER (PARTITION BY query_id ORDER BY again, similarity DESC, example_id))::INT AS rank, example_id, target_value, similarity FROM best QUALIFY rank <= 10""")
_thin = SUPPLY.replace("pool AS (SELECT * FROM masked WHERE n_name IS NOT NULL)", f"pool AS (SELECT * FROM masked WHERE n_name IS NOT NULL QUALIFY row_number() OVER (PARTITION BY n_name ORDER BY {h('s_suppkey', '1')}, s_suppkey) <= 2)")
oracle("topk_thinned_recall", f"""WITH e AS (WITH {topk(3)} SELECT * FROM ex), f AS (WITH {topk(3, setup=_thin)} SELECT * FROM ex),
j AS (SELECT coalesce(f.similarity >= e.similarity, false)::INT AS hit FROM e LEFT JOIN f USING (query_id, rank)) SELECT count(*) AS examples, sum(hit)::BIGINT AS found, round(avg(hit), 6) AS recall FROM j""")
_first = lambda setup: f"(WITH {topk(1, setup=setup)} SELECT m.s_suppkey, coalesce(n_name, target_value) AS v, n_name IS NULL AND target_value IS NOT NULL AS filled, s_phone, s_name FROM masked m LEFT JOIN ex ON query_id = s_suppkey)"
oracle("impute_two_targets", f"SELECT s_suppkey, a.v AS n_name, a.s_phone, a.s_name, b.v AS r_name, a.filled AS n_name_imputed, b.filled AS r_name_imputed FROM {_first(SUPPLY)} a JOIN {_first(REGION)} b USING (s_suppkey)")
oracle("long_cell_passages", """WITH near AS (SELECT item_id, doc_id, b.text AS a, d.text AS t FROM benchmark b CROSS JOIN documents d
WHERE EXISTS (SELECT 1 FROM range(1, length(b.text) - 98) s(i) WHERE contains(d.text, substr(b.text, s.i, 100))))
SELECT item_id, doc_id, (SELECT max(l.n) FROM range(100, length(a)+1) l(n), range(1, length(a)+1) s(i) WHERE s.i + l.n - 1 <= length(a) AND contains(t, substr(a, s.i, l.n))) AS length FROM near""")
oracle("retrieval_work", f"""WITH {MASKED}, a AS (SELECT count(DISTINCT c_phone) AS queries FROM masked WHERE n_name IS NULL), p AS (SELECT DISTINCT c_phone, n_name FROM masked WHERE n_name IS NOT NULL),
b AS (SELECT count(*) AS pool_rows, (SELECT count(*) FROM (SELECT DISTINCT n_name, length(c_phone) FROM p)) AS automata FROM p)
SELECT queries, pool_rows, queries * pool_rows AS pairs, queries * automata AS walks FROM a CROSS JOIN b""")


def geo_near(percent: int = 10, seed: str = "1", tag: str = "") -> str:
    """CTEs of the masked customers and near: the best similarity of each masked customer to each target value. A pair's
    longest common substring is found by joining on substrings, longest first."""
    subs = lambda name, rel, keep: f"{name}{tag} AS (SELECT DISTINCT {keep}, substr(c_phone, s.i, l.n) AS part, l.n AS n FROM {rel}, range(1, length(c_phone)+1) s(i), range(1, length(c_phone)-s.i+2) l(n))"
    return f"""{masked(mcar(percent, seed=seed), name=f'm{tag}')}, q{tag} AS (SELECT * FROM m{tag} WHERE n_name IS NULL), p{tag} AS (SELECT c_custkey, n_name, c_phone, length(c_phone) AS size FROM m{tag} WHERE n_name IS NOT NULL),
{subs('sq', f'q{tag}', 'c_custkey AS query_id, length(c_phone) AS qsize')}, {subs('sp', f'p{tag}', 'n_name, size, c_custkey')},
held{tag} AS (SELECT n_name, size, part, min(c_custkey) AS example_id FROM sp{tag} GROUP BY ALL),
meet{tag} AS (SELECT query_id, n_name AS target_value, round(max(n)::DOUBLE/greatest(qsize, size), 9) AS similarity, arg_min(example_id, (-n, example_id)) AS example_id FROM sq{tag} JOIN held{tag} USING (part) GROUP BY query_id, n_name, qsize, size),
every{tag} AS (SELECT * FROM meet{tag} UNION ALL SELECT q.c_custkey, v.n_name, 0.0, v.e FROM q{tag} q CROSS JOIN (SELECT n_name, min(c_custkey) AS e FROM p{tag} GROUP BY 1) v),
near{tag} AS (SELECT * FROM every{tag} QUALIFY row_number() OVER (PARTITION BY query_id, target_value ORDER BY similarity DESC, example_id) = 1)"""


def nearest(tag: str = "") -> str:
    return f"one{tag} AS (SELECT query_id, target_value AS answer FROM near{tag} QUALIFY row_number() OVER (PARTITION BY query_id ORDER BY similarity DESC, example_id) = 1)"


_right = lambda tag="": f"(SELECT count(*) AS cells, round(avg((coalesce(answer = truth, false))::INT::DOUBLE), 6) AS exact_match FROM q{tag} LEFT JOIN one{tag} ON query_id = c_custkey)"
oracle("geo_topk_k10", f"""WITH {GEO}, {geo_near()} SELECT query_id, (row_number() OVER (PARTITION BY query_id ORDER BY similarity DESC, example_id))::INT AS rank, example_id, target_value, similarity
FROM near QUALIFY rank <= 10""")
_vote = f"""WITH {GEO}, {geo_near()}, {nearest()}, {group_sample('p_all', 'c_custkey', 'n_name', 10, 10)}, {long_form('sample', 'c_custkey', 'n_name', ['c_phone'])}, {mined(0.75)},
found AS (SELECT c_custkey AS query_id, target_value AS found FROM q JOIN maxi ON contains(c_phone, pattern) QUALIFY row_number() OVER (PARTITION BY c_custkey ORDER BY length(pattern) DESC, target_value) = 1),
vote AS (SELECT query_id, coalesce(found, answer) AS answer FROM one FULL JOIN found USING (query_id))""".replace("sizes AS (SELECT n_name AS g", "p_all AS (SELECT * FROM m WHERE n_name IS NOT NULL), sizes AS (SELECT n_name AS g")
oracle("impute_pattern_vote", f"{_vote} SELECT query_id, answer FROM vote")
oracle("geo_end_to_end", f"{_vote} SELECT c_custkey AS query_id, truth, answer, answer = truth AS right FROM q LEFT JOIN vote ON query_id = c_custkey")
oracle("topk_all_attributes", f"WITH {topk(3, SIM2)} SELECT * FROM ex")
_holes = SUPPLY.replace("queries AS (SELECT * FROM masked", f"holes AS (SELECT * REPLACE (CASE WHEN {h('s_suppkey', '1', 's_phone')} % 100 >= 30 THEN s_phone END AS s_phone) FROM masked), queries AS (SELECT * FROM holes").replace("pool AS (SELECT * FROM masked", "pool AS (SELECT * FROM holes")
oracle("topk_null_cells", f"WITH {topk(3, SIM2, setup=_holes)} SELECT * FROM ex")


def drawn(k: int, deck: int = 1000) -> str:
    """CTE ex: k neighbours in the shuffled deck that a query draws."""
    return f"""decks AS (SELECT greatest(1, count(*) // {deck}) AS d FROM pool),
cards AS (SELECT s_suppkey AS example_id, n_name AS target_value, {h('s_suppkey', '1', 'deck')} % d AS deck, {h('s_suppkey', '1')} AS x FROM pool CROSS JOIN decks),
placed AS (SELECT *, row_number() OVER (PARTITION BY deck ORDER BY x, example_id) - 1 AS place, count(*) OVER (PARTITION BY deck) AS c FROM cards),
ex AS (SELECT q.s_suppkey AS query_id, r.i::INT AS rank, example_id, target_value FROM queries q CROSS JOIN decks CROSS JOIN range(1, {k} + 1) r(i)
JOIN placed ON deck = {h('q.s_suppkey', '1', 'deck')} % d AND ({h('q.s_suppkey', '1')} + r.i - 1) % c = place AND r.i <= c)"""


def cards(n: int) -> str:
    return f"cards AS (SELECT s_suppkey AS example_id, n_name AS target_value, row_number() OVER (ORDER BY {h('s_suppkey', '1')}, s_suppkey) - 1 AS place FROM pool QUALIFY place < {n}), many AS (SELECT count(*) AS c FROM cards)"


oracle("topk_random", f"WITH {SUPPLY}, {drawn(3)} SELECT * FROM ex")
RUN3 = f"{SUPPLY}, {cards(3)}, ex AS (SELECT q.s_suppkey AS query_id, (place+1)::INT AS rank, example_id, target_value FROM queries q CROSS JOIN cards)"
oracle("topk_random_run", f"WITH {RUN3} SELECT * FROM ex")
oracle("topk_fixed", f"WITH {SUPPLY} SELECT q.s_suppkey AS query_id, CASE p.s_suppkey WHEN 2 THEN 1 WHEN 3 THEN 2 ELSE 3 END AS rank, p.s_suppkey AS example_id, p.n_name AS target_value FROM queries q JOIN pool p ON p.s_suppkey IN (2,3,5)")
oracle("topk_embedding", f"""WITH e AS (SELECT vec_id, label::VARCHAR AS label, list_transform(embedding, lambda x: x::DOUBLE) AS v, {h('vec_id', '1')} % 100 < 10 AS asked FROM embeddings),
scored AS (SELECT q.vec_id AS query_id, p.vec_id AS example_id, p.label AS target_value, round(list_dot_product(q.v,p.v)/(sqrt(list_dot_product(q.v,q.v))*sqrt(list_dot_product(p.v,p.v))),6) AS similarity FROM e q JOIN e p ON q.asked AND NOT p.asked)
SELECT query_id, (row_number() OVER (PARTITION BY query_id ORDER BY similarity DESC, example_id))::INT AS rank, example_id, target_value, similarity FROM scored QUALIFY rank <= 3""")
oracle("retrieval_hit_rate", f"WITH {topk(10)}, per AS (SELECT k.i AS k, q.s_suppkey, max((e.target_value = q.truth)::INT) AS hit FROM queries q CROSS JOIN (VALUES (1),(3),(10)) k(i) LEFT JOIN ex e ON e.query_id=q.s_suppkey AND e.rank<=k.i GROUP BY ALL) SELECT count(*) AS cells, round(avg(coalesce(hit,0)),6) AS hit_rate, k FROM per GROUP BY k")

# ------------------------------------------------------------------ prompts and imputation
HEAD = "Fill in the missing value of n_name. Answer with the value only."
PROMPTS = f"""{topk(3)}, shots AS (SELECT query_id, string_agg('s_phone: '||p.s_phone||'; n_name: '||ex.target_value, chr(10) ORDER BY rank) AS body, count(*)::INT AS k FROM ex JOIN pool p ON p.s_suppkey=ex.example_id GROUP BY 1),
prompts AS (SELECT q.s_suppkey AS query_id, '{HEAD}'||chr(10)||coalesce(body||chr(10),'')||'s_phone: '||s_phone||'; n_name: ' AS prompt, coalesce(k,0) AS k FROM queries q LEFT JOIN shots ON query_id=q.s_suppkey)"""
oracle("prompts_k3", f"WITH {PROMPTS} SELECT query_id, prompt, k, sha256(prompt) AS prompt_hash FROM prompts")
oracle("prompts_zero_shot", f"WITH {SUPPLY}, z AS (SELECT s_suppkey AS query_id, '{HEAD}'||chr(10)||'s_phone: '||s_phone||'; n_name: ' AS prompt FROM queries) SELECT query_id, prompt, 0 AS k, sha256(prompt) AS prompt_hash FROM z")
words = lambda x: f"len(list_filter(regexp_split_to_array(coalesce({x},''), '[ \\t\\n\\r]+'), lambda w: w <> ''))"
oracle("prompt_tokens", f"WITH {PROMPTS} SELECT query_id, k::BIGINT AS k, {words('prompt')} AS tokens FROM prompts")
oracle("prompt_cost", f"""WITH {PROMPTS} SELECT count(*) AS prompts, sum({words('prompt')})::BIGINT AS all_tokens, round(avg({words('prompt')}),4) AS mean_tokens,
round({len(HEAD.split())} + avg(k) * 1 * (SELECT avg({words('s_phone')}) FROM sup), 4) AS formula_tokens FROM prompts""")
ALL6 = ["c_phone", "c_reviews", "c_name", "r_name", "c_mktsegment", "c_acctbal"]
oracle("token_reduction", f"WITH {GEO} SELECT sum({words('c_phone')})::BIGINT AS selected_tokens, sum({'+'.join(words(c) for c in ALL6)})::BIGINT AS all_tokens, round(1 - sum({words('c_phone')})/sum({'+'.join(words(c) for c in ALL6)}), 6) AS reduction FROM geo")
oracle("scripted_completion", f"WITH {topk(1)} SELECT query_id, target_value AS answer FROM ex")
oracle("impute_nearest_vote", f"""WITH {topk(3)} SELECT m.s_suppkey, coalesce(m.n_name, e.target_value) AS n_name, m.s_phone, m.s_name, m.is_masked, m.n_name IS NULL AND e.target_value IS NOT NULL AS n_name_imputed
FROM masked m LEFT JOIN ex e ON e.query_id = m.s_suppkey AND e.rank = 1""")
VOTE = "vote AS (SELECT query_id, target_value AS answer FROM (SELECT query_id, target_value, round(sum({w}),6) AS weight, min(rank) AS first FROM ex GROUP BY 1,2) QUALIFY row_number() OVER (PARTITION BY query_id ORDER BY weight DESC, first) = 1)"
_cell_of = lambda side, key: f"(SELECT s_phone FROM sup WHERE s_suppkey = {side}.{key})"
oracle("explain_rows", f"""WITH {topk(3)}, used AS (SELECT ex.*, (SELECT target_value FROM ex o WHERE o.query_id = ex.query_id AND o.rank = 1) AS answer, a.s_phone AS x, b.s_phone AS y
 FROM ex JOIN sup a ON a.s_suppkey = ex.query_id JOIN sup b ON b.s_suppkey = ex.example_id),
parts AS (SELECT query_id, example_id, substr(x, s.i, l.n) AS c, s.i AS i, l.n AS n FROM used, range(1, length(x)+1) s(i), range(1, length(x)-s.i+2) l(n) WHERE contains(y, substr(x, s.i, l.n))),
lon AS (SELECT query_id, example_id, c FROM parts QUALIFY row_number() OVER (PARTITION BY query_id, example_id ORDER BY n DESC, i) = 1)
SELECT query_id, answer, rank, example_id, target_value, similarity, 's_phone' AS attribute, coalesce(c, '') AS common FROM used LEFT JOIN lon USING (query_id, example_id)""")
oracle("impute_weighted_vote", f"WITH {topk(3)}, {VOTE.format(w='similarity')} SELECT * FROM vote")

# ------------------------------------------------------------------ baselines
oracle("fill_mode", f"WITH {MASKED} SELECT c_custkey AS query_id, (SELECT n_name FROM masked WHERE n_name IS NOT NULL GROUP BY 1 ORDER BY count(*) DESC, n_name LIMIT 1) AS answer FROM masked WHERE n_name IS NULL")
_mode_by = lambda key, rel="masked": f"(SELECT {key}, n_name AS answer FROM {rel} WHERE n_name IS NOT NULL GROUP BY {key}, n_name QUALIFY row_number() OVER (PARTITION BY {key} ORDER BY count(*) DESC, n_name) = 1)"
oracle("fill_mode_by_segment", f"WITH {MASKED} SELECT c_custkey AS query_id, answer FROM masked LEFT JOIN {_mode_by('c_mktsegment')} USING (c_mktsegment) WHERE n_name IS NULL")
BALANCE = f"bal AS (SELECT c_custkey, CASE WHEN {h('c_custkey', '1')} % 100 >= 10 THEN c_acctbal END AS c_acctbal FROM customer)"
oracle("fill_mean", f"WITH {BALANCE} SELECT c_custkey AS query_id, (SELECT round(avg(c_acctbal),4) FROM bal) AS answer FROM bal WHERE c_acctbal IS NULL")
oracle("fill_median", f"WITH {BALANCE} SELECT c_custkey AS query_id, (SELECT quantile_disc(c_acctbal,0.5) FROM bal) AS answer FROM bal WHERE c_acctbal IS NULL")
_equal = "+".join(f"(q.{c} = p.{c})::INT" for c in ALL6)
oracle("neighbour_object_sim", f"""WITH {MASKED} SELECT q.c_custkey AS query_id, p.n_name AS answer FROM masked q JOIN masked p ON q.n_name IS NULL AND p.n_name IS NOT NULL AND ({_equal}) > 0
QUALIFY row_number() OVER (PARTITION BY q.c_custkey ORDER BY ({_equal}) DESC, p.c_custkey) = 1""")
_two = ["r_name", "c_mktsegment"]
_pair = " ".join(f"LEFT JOIN (SELECT {a} AS k{i}, n_name AS v{i}, count(*) AS n{i} FROM masked WHERE n_name IS NOT NULL GROUP BY 1,2) t{i} ON t{i}.k{i}=q.{a} AND t{i}.v{i}=v.value" for i, a in enumerate(_two))
_dom = ", ".join(f"(SELECT count(DISTINCT {a}) FROM masked WHERE n_name IS NOT NULL) AS d{i}" for i, a in enumerate(_two))
_score = "ln(v.n/t.total)+" + "+".join(f"ln((coalesce(n{i},0)+0.1::DOUBLE)/(v.n+0.1::DOUBLE*d{i}))" for i in range(2))
oracle("probabilistic_repair", f"""WITH {MASKED}, v AS (SELECT n_name AS value, count(*) AS n FROM masked WHERE n_name IS NOT NULL GROUP BY 1), t AS (SELECT (SELECT sum(n) FROM v) AS total, {_dom})
SELECT q.c_custkey AS query_id, v.value AS answer FROM masked q CROSS JOIN v CROSS JOIN t {_pair} WHERE q.n_name IS NULL
QUALIFY row_number() OVER (PARTITION BY q.c_custkey ORDER BY round({_score},6) DESC, v.value) = 1""")
oracle("allattr_prompt", f"WITH {RUN3}, {VOTE.format(w='1.0')} SELECT * FROM vote")

# ------------------------------------------------------------------ measures and workloads
oracle("exact_match", f"WITH {topk(1)} SELECT count(*) AS cells, round(avg((coalesce(e.target_value = q.truth,false))::INT::DOUBLE),6) AS exact_match, round(avg((coalesce(lower(trim(e.target_value)) = lower(trim(q.truth)),false))::INT::DOUBLE),6) AS normalised FROM queries q LEFT JOIN ex e ON e.query_id=q.s_suppkey")
_tok = lambda x: f"list_filter(regexp_split_to_array(lower({x}), '[^\\p{{L}}\\p{{N}}]+'), lambda w: w <> '')"
oracle("rouge1", f"""WITH b AS (SELECT t.item_id, {_tok("coalesce(a.text, '')")} AS p, {_tok('t.text')} AS t FROM benchmark t LEFT JOIN benchmark a ON a.item_id + 1 = t.item_id),
c AS (SELECT item_id, len(p) AS np, len(t) AS nt, (SELECT coalesce(sum(least(len(list_filter(p, lambda x: x = w.u)), len(list_filter(t, lambda x: x = w.u)))),0) FROM (SELECT unnest(list_distinct(p)) AS u) w) AS both_ FROM b)
SELECT round(avg(CASE WHEN np>0 THEN both_/np ELSE 0 END),6) AS rouge1_precision, round(avg(CASE WHEN nt>0 THEN both_/nt ELSE 0 END),6) AS rouge1_recall, round(avg(CASE WHEN both_>0 THEN 2*both_/(np+nt) ELSE 0 END),6) AS rouge1_f1 FROM c""")
def arm(name: str, k: int, sim: str | None) -> str:
    """One row per masked supplier of an arm: whether the weighted vote over its k examples is right."""
    ex = f"{topk(k, sim)}" if sim else f"{SUPPLY}, {cards(k)}, ex AS (SELECT q.s_suppkey AS query_id, (place+1)::INT AS rank, example_id, target_value FROM queries q CROSS JOIN cards)"
    return f"(WITH {ex}, {VOTE.format(w='similarity' if sim else '1.0')} SELECT '{name}' AS arm, {k} AS k, coalesce((answer = truth)::INT, 0) AS exact FROM queries LEFT JOIN vote ON query_id = s_suppkey)"


ONE = similar([("q.s_phone", "p.s_phone")])
_arms = lambda k: [arm("all_random", k, None), arm("selected_random", k, None), arm("all_diverse", k, SIM2), arm("selected_diverse", k, ONE)]
oracle("ablation_cube", f"WITH arms AS ({' UNION ALL '.join(_arms(3))}) SELECT arm, k, count(*) AS cells, round(avg(exact), 6) AS exact_match FROM arms GROUP BY CUBE (arm, k)")
oracle("gain_table", f"""WITH arms AS ({' UNION ALL '.join(_arms(3) + _arms(10))}), per AS (SELECT k, round(avg(exact) FILTER (arm = 'selected_random'), 6) AS selected_random, round(avg(exact) FILTER (arm = 'selected_diverse'), 6) AS selected_diverse FROM arms GROUP BY k)
SELECT k, selected_random, selected_diverse, CASE WHEN selected_random > 0 THEN round((selected_diverse / selected_random - 1) * 100, 1) END AS gain FROM per""")
_runs = ", ".join(f"{geo_near(10, str(x), f'_s{x}')}, {nearest(f'_s{x}')}" for x in range(1, 6))
oracle("mean_std", f"WITH {GEO}, {_runs}, runs AS ({' UNION ALL '.join(f'SELECT * FROM {_right(f'_s{x}')}' for x in range(1, 6))}) SELECT 'nearest_vote' AS method, count(*) AS runs, round(avg(exact_match), 6) AS mean, round(stddev_samp(exact_match), 6) AS std FROM runs")
oracle("counters", f"WITH {MASKED} SELECT count(*) AS rows, round(avg((length(c_phone)+length(c_name))/2),4) AS mean_length, count(*) FILTER (n_name IS NOT NULL) AS complete_rows, 2 AS candidates, 1 AS selected FROM masked")
_sweep = ", ".join(f"{geo_near(r, tag=f'_r{r}')}, {nearest(f'_r{r}')}" for r in (10, 20, 30, 40, 50))
oracle("missing_rate_sweep", f"WITH {GEO}, {_sweep} {' UNION ALL '.join(f'SELECT {r} AS rate, cells, exact_match FROM {_right(f'_r{r}')}' for r in (10, 20, 30, 40, 50))}")
oracle("rouge1_answers", f"""WITH {GEO}, {geo_near()}, {nearest()}, t AS (SELECT list_filter(regexp_split_to_array(lower(coalesce(answer,'')), '[^\\p{{L}}\\p{{N}}]+'), lambda w: w <> '') AS a, list_filter(regexp_split_to_array(lower(truth), '[^\\p{{L}}\\p{{N}}]+'), lambda w: w <> '') AS b FROM q LEFT JOIN one ON query_id = c_custkey),
c AS (SELECT len(a) AS na, len(b) AS nb, len(list_intersect(a, b)) AS n FROM t)
SELECT round(avg(CASE WHEN na > 0 THEN n / na ELSE 0 END), 6) AS rouge1_precision, round(avg(CASE WHEN nb > 0 THEN n / nb ELSE 0 END), 6) AS rouge1_recall, round(avg(CASE WHEN n > 0 THEN 2 * n / (na + nb) ELSE 0 END), 6) AS rouge1_f1 FROM c""")
oracle("stream_window_counts", "SELECT strftime(date_trunc('day', ts), '%Y-%m-%d') AS window_start, event_type, count(*) AS events, count(*) FILTER (value IS NULL) AS missing FROM events GROUP BY 1,2")
oracle("stream_session_counts", """WITH g AS (SELECT user_id, ts, CASE WHEN ts >= lag(ts) OVER w + INTERVAL 30 MINUTE THEN 1 ELSE 0 END AS cut FROM events WINDOW w AS (PARTITION BY user_id ORDER BY ts)),
s AS (SELECT user_id, ts, sum(cut) OVER (PARTITION BY user_id ORDER BY ts ROWS UNBOUNDED PRECEDING) AS n FROM g)
SELECT user_id, strftime(min(ts), '%Y-%m-%d %H:%M:%S') AS session_start, count(*) AS events FROM s GROUP BY user_id, n""")
_deal = f"cards AS (SELECT n_name AS target_value, row_number() OVER (ORDER BY {h('c_custkey', '1')}, c_custkey) AS rank FROM p QUALIFY rank <= 10)"
_one_answer = lambda pick: f"(SELECT count(*) AS cells, round(avg((truth = a)::INT::DOUBLE), 6) AS exact_match FROM q CROSS JOIN ({pick}))"
_em = "(SELECT count(*) AS cells, round(avg((coalesce(answer = truth, false))::INT::DOUBLE), 6) AS exact_match FROM q LEFT JOIN {} ON query_id = c_custkey)"
oracle("small_model_comparison", f"""{_vote}, {_deal}
SELECT 'all attributes, random' AS method, 'weak' AS backend, * FROM {_one_answer('SELECT target_value AS a FROM cards WHERE rank = 1')}
UNION ALL SELECT 'all attributes, random', 'strong', * FROM {_one_answer('SELECT target_value AS a FROM cards GROUP BY 1 ORDER BY count(*) DESC, min(rank) LIMIT 1')}
UNION ALL SELECT 'localized', 'weak', * FROM {_em.format('one')} UNION ALL SELECT 'localized', 'strong', * FROM {_em.format('vote')}""")
oracle("order_ranks", """SELECT o_orderkey, o_custkey, row_number() OVER w AS place, ntile(4) OVER w AS quarter, rank() OVER s AS status_rank, dense_rank() OVER s AS status_dense_rank FROM orders
WINDOW w AS (PARTITION BY o_custkey ORDER BY o_totalprice DESC, o_orderkey), s AS (PARTITION BY o_custkey ORDER BY o_orderstatus)""")
oracle("order_windows", """SELECT o_orderkey, lag(o_orderkey) OVER w AS before, lead(o_orderkey) OVER w AS after, first_value(o_orderkey) OVER w AS first,
round(sum(o_totalprice) OVER (PARTITION BY o_custkey ORDER BY o_orderdate, o_orderkey ROWS UNBOUNDED PRECEDING), 2) AS running FROM orders WINDOW w AS (PARTITION BY o_custkey ORDER BY o_orderdate, o_orderkey)""")
oracle("segment_rollup", f"WITH {GEO} SELECT r_name, c_mktsegment, count(*) AS customers FROM geo GROUP BY ROLLUP (r_name, c_mktsegment)")
oracle("segment_grouping_sets", f"WITH {GEO} SELECT r_name, c_mktsegment, count(*) AS customers, count(DISTINCT n_name) AS nations FROM geo GROUP BY GROUPING SETS ((r_name), (c_mktsegment), ())")
oracle("distinct_values", f"WITH {GEO} " + " UNION ALL ".join(f"SELECT '{c}' AS attribute, count(DISTINCT {c}) AS exact, true AS within FROM geo" for c in ("c_phone", "c_name", "n_name")))
oracle("event_properties", "SELECT event_type, count(*) AS events, sum((props::JSON->>'k')::BIGINT)::BIGINT AS sum_k, max((props::JSON->>'k')::BIGINT) AS max_k FROM events GROUP BY 1")
_pair_of = lambda x: f"(WITH {group_sample('geo', 'c_custkey', 'n_name', 10, 10, x)} SELECT DISTINCT n_name, c_mktsegment FROM sample)"
oracle("pool_set_operations", f"WITH {GEO}, a AS {_pair_of('1')}, b AS {_pair_of('2')} SELECT *, 'both' AS part FROM (SELECT * FROM a INTERSECT SELECT * FROM b) UNION ALL SELECT *, 'first' FROM (SELECT * FROM a EXCEPT SELECT * FROM b)")
