"""DuckDB SQL for the corpora and methods, written from the definitions and not from the engine's plans."""

from __future__ import annotations

WORD = r"[^\x20\x09-\x0D]+"
_STYLE = rf"""concat_ws('|', CASE WHEN w <= 3 THEN '18' WHEN w <= 6 THEN '14' ELSE '12' END,
  CASE WHEN regexp_matches(line, '[A-Za-zÀ-ÿ]') AND NOT regexp_matches(line, '[a-zß-öø-ÿ]') THEN 'C' ELSE 'c' END,
  CASE WHEN right(line, 1) IN ('.', '!', '?', ':', ',') THEN right(line, 1) ELSE '' END,
  CASE WHEN regexp_matches(line, '^\d+[.)] ') THEN 'n' ELSE '' END)"""

PHRASES = rf"""
line0 AS (SELECT doc_id, unnest(ls) AS line, generate_subscripts(ls, 1) - 1 AS ln FROM (SELECT doc_id, string_split(text, chr(10)) AS ls FROM documents)),
line1 AS (SELECT *, len(regexp_extract_all(line, '{WORD}')) AS w FROM line0),
phrase AS (SELECT doc_id, ln, line, w, CASE WHEN w <= 10 AND NOT contains(line, ' | ') THEN {_STYLE} END AS style FROM line1 WHERE w > 0)"""


def _fold(source: str) -> str:
    """Headers from rows (doc_id, ln, style or null, rk, title, w) of ``source``."""
    return f"""SELECT doc_id, CAST(pos AS INTEGER) AS pos, max(style) AS style, max(rk) AS rk, max(title) AS title, CAST(coalesce(sum(w) FILTER (style IS NULL), 0) AS BIGINT) AS body_words
    FROM (SELECT *, count(style) OVER (PARTITION BY doc_id ORDER BY ln) - 1 AS pos FROM {source}) GROUP BY doc_id, pos"""


LINES = f"""{PHRASES},
lrow AS (SELECT doc_id, ln, style, CASE left(style, 2) WHEN '18' THEN 2 WHEN '14' THEN 3 WHEN '12' THEN 4 END AS rk, CASE WHEN style IS NOT NULL THEN line END AS title, w FROM phrase
  UNION ALL SELECT doc_id, -1, 'ROOT', 0, '', 0 FROM documents),
h AS ({_fold("lrow")})"""


def composite(size: int) -> str:
    single = LINES.replace("\nh AS (", "\nsingle AS (")
    return f"""{single},
near AS (SELECT d.doc_id AS comp_id, x.doc_id, row_number() OVER (PARTITION BY d.doc_id ORDER BY (x.doc_id * 7919 + d.doc_id * 104729) % 1000003, x.doc_id) AS place FROM documents d JOIN documents x ON d.lang = x.lang AND d.doc_id <> x.doc_id),
member AS (SELECT comp_id, doc_id FROM near WHERE place <= {size - 1} UNION ALL SELECT doc_id, doc_id FROM documents),
slotted AS (SELECT *, row_number() OVER (PARTITION BY comp_id ORDER BY (doc_id * 31 + comp_id * 17) % 1009, doc_id) AS slot FROM member),
crow AS (SELECT comp_id AS doc_id, slot, pos AS inner_pos, CASE WHEN pos = 0 THEN 'TITLE' ELSE style END AS style, CASE WHEN pos = 0 THEN 1 ELSE rk END AS rk,
  CASE WHEN pos = 0 THEN 'Document ' || s.doc_id ELSE title END AS title, body_words FROM slotted s JOIN single USING (doc_id)
  UNION ALL SELECT doc_id, 0, 0, 'ROOT', 0, '', 0 FROM documents),
h AS (SELECT doc_id, CAST(row_number() OVER (PARTITION BY doc_id ORDER BY slot, inner_pos) - 1 AS INTEGER) AS pos, style, rk, title, body_words FROM crow)"""


HTML = rf"""
part0 AS (SELECT page_id AS doc_id, unnest(ps) AS part, generate_subscripts(ps, 1) AS ln FROM (SELECT page_id, regexp_extract_all(regexp_replace(html, '(?s)<(script|style)[^>]*>.*?</(script|style)>', '', 'g'), '<[a-z][a-z0-9]*[^>]*>[^<]*') AS ps FROM pages)),
part1 AS (SELECT doc_id, ln, regexp_extract(part, '^<([a-z][a-z0-9]*)', 1) AS tag, trim(regexp_replace(part, '^<[^>]*>', '')) AS said FROM part0),
part2 AS (SELECT *, CASE tag WHEN 'title' THEN 0 WHEN 'nav' THEN 1 WHEN 'h1' THEN 1 WHEN 'footer' THEN 1 WHEN 'li' THEN 2 WHEN 'b' THEN 2 END AS rk FROM part1),
prow AS (SELECT doc_id, ln, CASE WHEN rk IS NOT NULL THEN tag END AS style, rk, CASE WHEN rk IS NOT NULL THEN said END AS title, len(regexp_extract_all(said, '{WORD}')) AS w FROM part2),
h AS (SELECT * FROM ({_fold("prow")}) WHERE pos >= 0)"""

DIALOGUE = rf"""
said AS (SELECT conv_id AS doc_id, turn, role, coalesce(text, '') AS text, string_split(coalesce(text, ''), chr(10))[1] AS title FROM conversations),
trow AS (SELECT doc_id, turn, role AS style, CASE WHEN role = 'assistant' THEN 2 ELSE 1 END AS rk, title, len(regexp_extract_all(text, '{WORD}')) - len(regexp_extract_all(title, '{WORD}')) AS body_words FROM said
  UNION ALL SELECT DISTINCT doc_id, -1, 'ROOT', 0, '', 0 FROM said),
h AS (SELECT doc_id, CAST(row_number() OVER (PARTITION BY doc_id ORDER BY turn) - 1 AS INTEGER) AS pos, style, rk, title, CAST(body_words AS BIGINT) AS body_words FROM trow)"""


def ledger(variant: str) -> str:
    customer = {"all": "'customer ' || c_mktsegment", "parity": "'customer ' || (place % 2)"}.get(variant, "'customer'")
    order = "'order ' || o_orderpriority" if variant in ("leaf", "all") else "'order'"
    memo = """
  UNION ALL SELECT n_regionkey, n_nationkey, -1, -1, 1, 'memo', 2, 'Memo', 0 FROM nat WHERE place = 1
  UNION ALL SELECT n_regionkey, n_nationkey, c_custkey, o_orderkey, 1, 'memo', 4, 'Memo', 0 FROM ord WHERE place >= 1 AND o_orderstatus = 'P'"""
    return rf"""
nat AS (SELECT *, row_number() OVER (PARTITION BY n_regionkey ORDER BY n_nationkey) - 1 AS place FROM nation),
cus AS (SELECT * FROM customer JOIN nat ON c_nationkey = n_nationkey),
item AS (SELECT l_orderkey, sum(len(regexp_extract_all(p_name || ' ' || s_name, '{WORD}'))) AS w FROM lineitem JOIN part ON l_partkey = p_partkey JOIN supplier ON l_suppkey = s_suppkey GROUP BY 1),
ord AS (SELECT * FROM orders JOIN cus ON o_custkey = c_custkey LEFT JOIN item ON l_orderkey = o_orderkey),
grow AS (SELECT r_regionkey AS doc_id, -1 AS n, -1 AS c, -1 AS o, 0 AS sub, 'region' AS style, 0 AS rk, r_name AS title, 0 AS body_words FROM region
  UNION ALL SELECT n_regionkey, n_nationkey, -1, -1, 0, 'nation', 1, n_name, 0 FROM nat
  UNION ALL SELECT n_regionkey, n_nationkey, c_custkey, -1, 0, {customer}, 2, c_name, 0 FROM cus
  UNION ALL SELECT n_regionkey, n_nationkey, c_custkey, o_orderkey, 0, {order}, 3, 'Order ' || o_orderkey, coalesce(w, 0) FROM ord{memo if variant == "memo" else ""}),
h AS (SELECT CAST(doc_id AS BIGINT) AS doc_id, CAST(row_number() OVER (PARTITION BY doc_id ORDER BY n, c, o, sub) - 1 AS INTEGER) AS pos, style, rk, title, CAST(body_words AS BIGINT) AS body_words FROM grow)"""


CORPORA = {"lines": LINES, "composite1": composite(1), "composite4": composite(4), "composite8": composite(8), "html": HTML, "dialogue": DIALOGUE, **{v: ledger(v) for v in ("level", "leaf", "parity", "memo", "all")}}

GROUPS = """
g0 AS (SELECT doc_id, style, min(pos) AS opener, count(*) AS n_nodes FROM h GROUP BY ALL),
g1 AS (SELECT *, CAST(row_number() OVER (PARTITION BY doc_id ORDER BY opener) - 1 AS INTEGER) AS g FROM g0),
grp AS (SELECT a.*, b.g AS prev_g FROM g1 a LEFT JOIN h p ON p.doc_id = a.doc_id AND p.pos = a.opener - 1 LEFT JOIN g1 b ON b.doc_id = p.doc_id AND b.style = p.style)"""


def depths(k: str, name: str) -> str:
    """sd by group for the blend with expression ``k``, one group after the other."""
    return f"""
{name}_scan(doc_id, i, ds) AS (SELECT doc_id, 0, [CAST(0 AS DOUBLE)] FROM grp WHERE g = 0
  UNION ALL SELECT s.doc_id, s.i + 1, list_append(s.ds, round(({k}) * s.ds[x.prev_g + 1] + (1 - ({k})) * list_max(s.ds) + 1, 9)) FROM {name}_scan s JOIN grp x ON x.doc_id = s.doc_id AND x.g = s.i + 1),
{name}_all AS (SELECT doc_id, ds FROM {name}_scan QUALIFY row_number() OVER (PARTITION BY doc_id ORDER BY i DESC) = 1),
{name}_sd AS (SELECT grp.doc_id, grp.style, grp.g, ds[grp.g + 1] AS sd FROM grp JOIN {name}_all USING (doc_id)),
{name}_h AS (SELECT h.*, sd FROM h JOIN {name}_sd USING (doc_id, style))"""


def tree(source: str, key: str, name: str) -> str:
    """Parents and span ends of ``source`` by its depth column ``key``."""
    return f"""
{name} AS (SELECT a.doc_id, a.pos,
  (SELECT max(b.pos) FROM {source} b WHERE b.doc_id = a.doc_id AND b.pos < a.pos AND b.{key} < a.{key}) AS parent_pos,
  CAST(coalesce((SELECT min(b.pos) FROM {source} b WHERE b.doc_id = a.doc_id AND b.pos > a.pos AND b.{key} <= a.{key}), (SELECT max(pos) + 1 FROM {source} b WHERE b.doc_id = a.doc_id)) AS INTEGER) AS span_end
  FROM {source} a)"""


DEEP = "deep AS (SELECT doc_id, pos, lag(pos) OVER (PARTITION BY doc_id ORDER BY pos) AS parent_pos, CAST(max(pos) OVER (PARTITION BY doc_id) + 1 AS INTEGER) AS span_end FROM h)"
WIDE = "wide AS (SELECT doc_id, pos, CASE WHEN pos > 0 THEN 0 END AS parent_pos, CAST(CASE WHEN pos = 0 THEN max(pos) OVER (PARTITION BY doc_id) + 1 ELSE coalesce(lead(pos) OVER (PARTITION BY doc_id ORDER BY pos), max(pos) OVER (PARTITION BY doc_id) + 1) END AS INTEGER) AS span_end FROM h)"


def trees(*names: str) -> str:
    """CTEs of the named approaches and of the truth."""
    ks = {"local": "1", "global": "0", "half": "0.5"}
    made = [depths(ks[n], n) + "," + tree(f"{n}_h", "sd", f"{n}_t") for n in names if n in ks]
    made += [{"deep": DEEP, "wide": WIDE}[n] for n in names if n in ("deep", "wide")]
    return ",".join([GROUPS, *made, tree("h", "rk", "true_t")])


def union_trees(*names: str) -> str:
    return "tr AS (" + " UNION ALL ".join(f"SELECT '{n}' AS approach, * FROM {n if n in ('deep', 'wide') else n + '_t'}" for n in names) + ")"
