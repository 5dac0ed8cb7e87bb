"""DuckDB SQL of the fixtures and of the method, its rounds unrolled to a fixed depth."""

from __future__ import annotations

from ..functions.minhash import PRIME, coefficients
from ..sources.tables import LINEITEM_KEY
from .fixtures import SEGMENTS

WORDS = "list_distinct(regexp_extract_all(lower({c}), '[\\p{{L}}\\p{{N}}]+'))"


def words(c: str) -> str:
    return WORDS.format(c=c)


def identity(attribute: str, value: str) -> str:
    return f"md5('{attribute}' || chr(31) || lower(trim({value})))"


def index(table: str, rid: str, attributes: list[tuple[str, str]]) -> str:
    """SELECT of (rid, key) with one identity key per attribute."""
    return " UNION ALL ".join(f"SELECT {rid} AS rid, {identity(a, v)} AS key FROM {table} WHERE {v} IS NOT NULL AND trim({v}) <> ''" for a, v in attributes)


_text = lambda c: f"CAST({c} AS VARCHAR)"
_long = lambda c: f"CAST(CAST({c} AS BIGINT) AS VARCHAR)"

PART = index("part", "p_partkey", [("p_name", "p_name"), ("p_brand", "p_brand"), ("p_type", "p_type"), ("p_size", _text("p_size")), ("p_retailprice", _long("round(p_retailprice * 100)"))])
ORDERS = index("orders", "o_orderkey", [("o_custkey", _text("o_custkey")), ("o_orderstatus", "o_orderstatus"), ("o_orderdate", "strftime(o_orderdate, '%Y-%m-%d')"), ("o_orderpriority", "o_orderpriority"), ("o_totalprice", _long("floor(o_totalprice / 10000)"))])
CUSTOMER = index("customer", "c_custkey", [("c_nationkey", _text("c_nationkey")), ("c_mktsegment", "c_mktsegment"), ("bal_bin", _long("floor(c_acctbal / 500)"))])
_next = "CASE c_mktsegment " + " ".join(f"WHEN '{a}' THEN '{b}'" for a, b in zip(SEGMENTS, SEGMENTS[1:] + SEGMENTS[:1], strict=True)) + " END"
VOTER_ROWS = f"""(SELECT 2 * c_custkey AS rid, c_name, c_nationkey, c_mktsegment, floor(c_acctbal / 500) AS bal_bin FROM customer UNION ALL
SELECT 2 * c_custkey + 1, CASE WHEN c_custkey % 7 = 0 THEN replace(c_name, 'Customer', 'Customr') ELSE c_name END, CASE WHEN c_custkey % 5 = 0 THEN (c_nationkey + 1) % 25 ELSE c_nationkey END,
CASE WHEN c_custkey % 11 = 0 THEN {_next} ELSE c_mktsegment END, floor((c_acctbal + CASE WHEN c_custkey % 3 = 0 THEN 1000 ELSE 0 END) / 500) FROM customer)"""
VOTER = index(VOTER_ROWS, "rid", [("c_name", "c_name"), ("c_nationkey", _text("c_nationkey")), ("c_mktsegment", "c_mktsegment"), ("bal_bin", _long("bal_bin"))])
DOCS = f"SELECT rid, md5(t) AS key FROM (SELECT doc_id AS rid, unnest({words('text')}) AS t FROM documents)"
LINK = f"SELECT rid, md5(t) AS key FROM (SELECT 2 * doc_id AS rid, unnest({words('text')}) AS t FROM documents UNION ALL SELECT 2 * item_id + 1, unnest({words('text')}) FROM benchmark)"
STRIPPED = (
    "trim(regexp_replace(replace(replace(replace(replace(replace(regexp_replace(regexp_replace(html, '(?is)<(script|style)[^>]*>.*?</(script|style)>', ' ', 'g'), '(?s)<[^>]*>', ' ', 'g'), "
    "'&lt;', '<'), '&gt;', '>'), '&quot;', '\"'), '&nbsp;', ' '), '&amp;', '&'), '\\s+', ' ', 'g'))"
)
PAGES = f"SELECT rid, md5(t) AS key FROM (SELECT page_id AS rid, unnest({words(STRIPPED)}) AS t FROM pages)"
LINE_ROWS = f"(SELECT row_number() OVER (ORDER BY {', '.join(LINEITEM_KEY)}) AS rid, * FROM lineitem)"


def lineitem(copies: int = 1, statuses: int = 1) -> str:
    hundred = lambda c: _long(f"round({c} * 100)")
    attributes = [("l_partkey", _text("l_partkey")), ("l_suppkey", _text("l_suppkey")), *((c, hundred(c)) for c in ("l_quantity", "l_discount", "l_tax")), ("l_returnflag", "l_returnflag"), ("l_linestatus", "l_linestatus")]
    attributes += [(f"l_shipdate{i or ''}", "strftime(l_shipdate, '%Y-%m-%d')") for i in range(copies)] + [(f"l_linestatus{i}", "l_linestatus") for i in range(1, statuses)]
    return index(LINE_ROWS, "rid", attributes)


def minima(tokens: str, m: int) -> str:
    """SELECT of (rid, i, mh) from a SELECT of (rid, t)."""
    co = ", ".join(f"({i}, {a}, {c})" for i, (a, c) in enumerate(coefficients(m)))
    return f"SELECT rid, i, min((a * h + c) % {PRIME}) AS mh FROM (SELECT rid, CAST('0x' || substr(md5(t), 1, 7) AS BIGINT) AS h FROM ({tokens})) AS x, (VALUES {co}) AS co(i, a, c) GROUP BY rid, i"


def lsh(tokens: str, label: str, bands: int, width: int) -> str:
    """SELECT of (rid, band, key)."""
    return f"SELECT rid, i // {width} AS band, md5('{label}' || chr(31) || CAST(i // {width} AS VARCHAR) || chr(31) || string_agg(CAST(mh AS VARCHAR), '-' ORDER BY i)) AS key FROM ({minima(tokens, bands * width)}) GROUP BY rid, i // {width}"


DOC_TOKENS = f"SELECT doc_id AS rid, unnest({words('text')}) AS t FROM documents"


def docs_lsh(bands: int, width: int) -> str:
    return f"SELECT rid, key FROM ({lsh(DOC_TOKENS, 'text', bands, width)})"


def rounds(base: str, cap: int, depth: int, key_cap: int = 80, thousandths: int = 900, p: str = "") -> str:
    """CTEs of the method over a SELECT of (rid, key); {p}pairs is its result. Twins have equal lists of ids."""
    out = [f"{p}k0 AS MATERIALIZED (SELECT rid, key, CAST(NULL AS BIGINT) AS psize FROM ({base}))"]
    for t in range(depth):
        k, st, ov, sv, held = (f"{p}{x}{t}" for x in ("k", "st", "ov", "sv", "in"))
        out += [
            f"{st} AS MATERIALIZED (SELECT key, count(*) AS size, min(psize) AS psize FROM {k} GROUP BY key)",
            f"{p}fit{t} AS (SELECT rid, key, size FROM {k} JOIN {st} USING (key) WHERE size BETWEEN 2 AND {cap})",
            f"{ov} AS (SELECT key, size FROM {st} WHERE size > {cap} AND (psize IS NULL OR size * 1000 <= psize * {thousandths}))",
            f"{p}id{t} AS MATERIALIZED (SELECT key, any_value(o.size) AS size, md5(string_agg(CAST(rid AS VARCHAR), ',' ORDER BY rid)) AS ids FROM {k} JOIN {ov} o USING (key) GROUP BY key)",
            f"{sv} AS MATERIALIZED (SELECT min(key) AS key, size FROM {p}id{t} GROUP BY ids, size)",
            f"{held} AS MATERIALIZED (SELECT rid, key, {sv}.size AS size FROM {k} JOIN {sv} USING (key))",
            f"{p}c{t} AS (SELECT rid FROM {held} GROUP BY rid HAVING count(*) BETWEEN 2 AND {key_cap})",
            f"{p}k{t + 1} AS MATERIALIZED (SELECT a.rid, md5(unhex(a.key) || unhex(b.key)) AS key, least(a.size, b.size) AS psize FROM {held} a JOIN {held} b ON a.rid = b.rid AND a.key < b.key JOIN {p}c{t} c ON c.rid = a.rid)",
        ]
    out += [
        f"{p}fit AS MATERIALIZED ({' UNION ALL '.join(f'SELECT * FROM {p}fit{t}' for t in range(depth))})",
        f"{p}every AS (SELECT a.rid AS rid1, b.rid AS rid2, a.key, a.size FROM {p}fit a JOIN {p}fit b ON a.key = b.key AND a.rid < b.rid)",
        f"{p}pairs AS (SELECT rid1, rid2, key, size FROM (SELECT *, row_number() OVER (PARTITION BY rid1, rid2 ORDER BY size DESC, key) AS nth FROM {p}every) WHERE nth = 1)",
    ]
    return ",\n".join(out)


def cap_drop(base: str, cap: int, p: str = "") -> str:
    """CTE {p}capped: distinct pairs of top-level blocks up to cap."""
    return (
        f"{p}cb AS MATERIALIZED (SELECT rid, key FROM ({base})), {p}cs AS (SELECT key FROM {p}cb GROUP BY key HAVING count(*) BETWEEN 2 AND {cap}), "
        f"{p}cf AS MATERIALIZED (SELECT rid, key FROM {p}cb JOIN {p}cs USING (key)), {p}capped AS (SELECT DISTINCT a.rid AS rid1, b.rid AS rid2 FROM {p}cf a JOIN {p}cf b ON a.key = b.key AND a.rid < b.rid)"
    )


def all_pairs(base: str, p: str = "") -> str:
    return f"{p}ab AS MATERIALIZED (SELECT rid, key FROM ({base})), {p}naive AS (SELECT DISTINCT a.rid AS rid1, b.rid AS rid2 FROM {p}ab a JOIN {p}ab b ON a.key = b.key AND a.rid < b.rid)"


def meta(base: str, weight: str, how: str | None, p: str = "") -> str:
    """CTEs {p}edge (rid1, rid2, w) and, with a pruning, {p}kept."""
    w = {
        "cbs": "c", "arcs": "arcs", "js": "c / (b1 + b2 - c)", "ecbs": "c * ln(n / b1) * ln(n / b2)", "ejs": "c / (b1 + b2 - c) * ln(e / d1) * ln(e / d2)",
        "chi2": "CASE WHEN b1 * b2 * (n - b1) * (n - b2) > 0 THEN n * pow(c * (n - b1 - b2 + c) - (b1 - c) * (b2 - c), 2) / (b1 * b2 * (n - b1) * (n - b2)) ELSE 0 END",
    }[weight]
    out = [
        f"{p}mb AS MATERIALIZED (SELECT rid, key FROM ({base}))",
        f"{p}post AS MATERIALIZED (SELECT rid, key, size FROM {p}mb JOIN (SELECT key, count(*) AS size FROM {p}mb GROUP BY key HAVING count(*) > 1) USING (key))",
        f"{p}raw AS MATERIALIZED (SELECT a.rid AS rid1, b.rid AS rid2, CAST(count(*) AS DOUBLE) AS c, sum(2.0 / (a.size * (a.size - 1))) AS arcs FROM {p}post a JOIN {p}post b ON a.key = b.key AND a.rid < b.rid GROUP BY 1, 2)",
        f"{p}deg AS MATERIALIZED (SELECT rid, CAST(count(*) AS DOUBLE) AS b FROM {p}post GROUP BY rid)",
        f"{p}ends AS (SELECT rid1 AS rid FROM {p}raw UNION ALL SELECT rid2 FROM {p}raw)",
        f"{p}gd AS MATERIALIZED (SELECT rid, CAST(count(*) AS DOUBLE) AS d FROM {p}ends GROUP BY rid)",
        f"{p}edge AS MATERIALIZED (SELECT rid1, rid2, round({w}, 9) AS w FROM (SELECT r.*, x.b AS b1, y.b AS b2, gx.d AS d1, gy.d AS d2, (SELECT CAST(count(DISTINCT key) AS DOUBLE) FROM {p}post) AS n, (SELECT CAST(count(*) AS DOUBLE) FROM {p}raw) AS e "
        f"FROM {p}raw r JOIN {p}deg x ON x.rid = rid1 JOIN {p}deg y ON y.rid = rid2 JOIN {p}gd gx ON gx.rid = rid1 JOIN {p}gd gy ON gy.rid = rid2))",
    ]
    if weight in ("cbs", "arcs"):  # no degrees are asked for
        out[3:] = [f"{p}edge AS MATERIALIZED (SELECT rid1, rid2, round({w}, 9) AS w FROM {p}raw)"]
    if how:
        out.append(f"{p}node AS MATERIALIZED (SELECT rid1 AS node, rid1, rid2, w FROM {p}edge UNION ALL SELECT rid2, rid1, rid2, w FROM {p}edge)")
        bar = f"(SELECT node, {'max(w)' if how == 'local_max' else 'round(avg(w), 9)'} AS bar FROM {p}node GROUP BY node)"
        best = f"(SELECT *, row_number() OVER (PARTITION BY node ORDER BY w DESC, rid1, rid2) AS nth FROM {p}node)"
        k = f"(SELECT greatest(1, count(*) // (SELECT count(DISTINCT node) FROM {p}node) - 1) FROM {p}post)"
        both = f"SELECT rid1, rid2 FROM {p}edge JOIN {bar} x ON x.node = rid1 JOIN {bar} y ON y.node = rid2 WHERE"
        out.append(
            f"{p}kept AS ("
            + {
                "wep": f"SELECT rid1, rid2 FROM {p}edge WHERE w >= (SELECT round(avg(w), 9) FROM {p}edge)",
                "cep": f"SELECT rid1, rid2 FROM {p}edge ORDER BY w DESC, rid1, rid2 LIMIT (SELECT count(*) // 2 FROM {p}post)",
                "wnp": f"{both} w >= x.bar OR w >= y.bar",
                "rwnp": f"{both} w >= x.bar AND w >= y.bar",
                "local_max": f"{both} w >= (x.bar + y.bar) / 4.0",
                "cnp": f"SELECT DISTINCT rid1, rid2 FROM {best} WHERE nth <= {k}",
                "rcnp": f"SELECT rid1, rid2 FROM {best} WHERE nth <= {k} GROUP BY rid1, rid2 HAVING count(*) = 2",
            }[how]
            + ")"
        )
    return ",\n".join(out)


def truth_docs(least: float = 0.8, p: str = "") -> str:
    """CTE {p}truth: document pairs by brute force over shared words."""
    return (
        f"{p}tw AS MATERIALIZED ({DOC_TOKENS}), {p}tn AS (SELECT rid, count(*) AS n FROM {p}tw GROUP BY rid), "
        f"{p}tc AS (SELECT a.rid AS rid1, b.rid AS rid2, count(*) AS c FROM {p}tw a JOIN {p}tw b ON a.t = b.t AND a.rid < b.rid GROUP BY 1, 2), "
        f"{p}tj AS MATERIALIZED (SELECT rid1, rid2, CAST(c AS DOUBLE) / (x.n + y.n - c) AS jaccard FROM {p}tc JOIN {p}tn x ON x.rid = rid1 JOIN {p}tn y ON y.rid = rid2), {p}truth AS (SELECT rid1, rid2 FROM {p}tj WHERE jaccard >= {least})"
    )


PART_TRUTH = "SELECT a.p_partkey AS rid1, b.p_partkey AS rid2 FROM part a JOIN part b USING (p_name, p_brand, p_type) WHERE a.p_partkey < b.p_partkey"
VOTER_TRUTH = "SELECT 2 * c_custkey AS rid1, 2 * c_custkey + 1 AS rid2 FROM customer"


def measured(pairs: str, truth: str) -> str:
    """SELECT of pairs, hits, total, pc, pq."""
    hits = f"(SELECT count(*) FROM (SELECT rid1, rid2 FROM ({pairs}) INTERSECT SELECT rid1, rid2 FROM ({truth})))"
    many = lambda x: f"(SELECT count(*) FROM (SELECT DISTINCT rid1, rid2 FROM ({x})))"
    share = lambda of: f"round(CASE WHEN {of} > 0 THEN CAST(hits AS DOUBLE) / {of} ELSE 0 END, 6)"
    return f"SELECT pairs, hits, total, {share('total')} AS pc, {share('pairs')} AS pq FROM (SELECT {many(pairs)} AS pairs, {hits} AS hits, {many(truth)} AS total)"
