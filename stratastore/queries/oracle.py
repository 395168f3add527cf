"""Pieces of DuckDB SQL: contents, cuts, trees, keys and costs, said a second time in another language."""

from __future__ import annotations

from ..functions import crypto, rolling
from ..params import StoreParams

DOCUMENTS = "SELECT CAST(doc_id AS VARCHAR) AS content_id, doc_id AS version, encode(text) AS body FROM documents WHERE text IS NOT NULL"
PAGES = "SELECT CAST(page_id AS VARCHAR) AS content_id, page_id AS version, encode(html) AS body FROM pages WHERE html IS NOT NULL"
PASSAGES = "SELECT CAST(item_id AS VARCHAR) AS content_id, item_id AS version, encode(text) AS body FROM benchmark WHERE text IS NOT NULL"
CONVERSATIONS = """SELECT CAST(conv_id AS VARCHAR) || ':' || CAST(turn AS VARCHAR) AS content_id, turn AS version,
  encode(string_agg(text, chr(10)) OVER (PARTITION BY conv_id ORDER BY turn ROWS BETWEEN UNBOUNDED PRECEDING AND CURRENT ROW)) AS body FROM conversations"""
EMBEDDINGS = """SELECT CAST(vec_id AS VARCHAR) AS content_id, vec_id AS version,
  encode(array_to_string(list_transform(embedding, lambda x: CAST(CAST(floor(CAST(x AS DOUBLE) * 1000000) AS BIGINT) AS VARCHAR)), ',')) AS body FROM embeddings"""


def _money(c: str) -> str:
    return f"CAST(CAST({c} AS DECIMAL(18,2)) AS VARCHAR)"


def _text(*columns: str) -> str:
    return "concat_ws('|', " + ", ".join(columns) + ")"


ORDER_LINE = _text("CAST(o_orderkey AS VARCHAR)", "CAST(o_custkey AS VARCHAR)", "o_orderstatus", _money("o_totalprice"), "strftime(o_orderdate, '%Y-%m-%d')", "o_orderpriority")
LINEITEM_LINE = _text(*[f"CAST({c} AS VARCHAR)" for c in ("l_orderkey", "l_linenumber", "l_partkey", "l_suppkey")], *[_money(c) for c in ("l_quantity", "l_extendedprice", "l_discount", "l_tax")], "l_returnflag", "l_linestatus", "strftime(l_shipdate, '%Y-%m-%d')")
EVENT_LINE = _text("CAST(event_id AS VARCHAR)", "strftime(ts, '%Y-%m-%d %H:%M:%S')", "CAST(user_id AS VARCHAR)", "event_type", _money('"value"'), "props")


def _snapshots(table: str, at: str, line: str, period: str, series: str) -> str:
    return f"""SELECT '{series}:' || CAST(q.version AS VARCHAR) AS content_id, q.version AS version, encode(string_agg(r.line, chr(10) ORDER BY lpad(CAST(r."at" AS VARCHAR), 12, '0') || r.line)) AS body
  FROM (SELECT {at} AS "at", {line} AS line, {period} AS p FROM {table}) r
  JOIN (SELECT p, row_number() OVER (ORDER BY p) AS version FROM (SELECT DISTINCT {period} AS p FROM {table}) WHERE p IS NOT NULL) q ON r.p <= q.p GROUP BY q.version"""


def _months(c: str, months: int) -> str:
    return f"CAST(floor((year({c}) * 12 + month({c}) - 1) / {months}.0) AS BIGINT)"


ORDERS = _snapshots("orders", "o_orderkey", ORDER_LINE, _months("o_orderdate", 3), "orders")
LINEITEM = _snapshots("lineitem", "l_orderkey", LINEITEM_LINE, _months("l_shipdate", 1), "lineitem")
EVENTS = _snapshots("events", "event_id", EVENT_LINE, "CAST(strftime(ts, '%Y%m%d') AS BIGINT)", "events")


def random_contents(seed: int, n: int, count: int) -> str:
    return f"""SELECT 'random:' || CAST(s AS VARCHAR) AS content_id, s AS version, unhex(string_agg(sha256(CAST(s AS VARCHAR) || ':' || CAST(i AS VARCHAR)), '' ORDER BY i))[1:{n}] AS body
  FROM range({seed}, {seed + count}) a(s), range({-(-n // 32)}) b(i) GROUP BY s"""


def tag(v: str, p: StoreParams) -> str:
    """Lower-case hex of the tag of a blob."""
    if p.protect == "hash":
        return f"sha256({v})"
    inner, outer = (x.hex() for x in crypto.pads(p.mac_key))
    return f"sha256(unhex('{outer}') || unhex(sha256(unhex('{inner}') || {v})))"


def height(n: str, p: StoreParams, top: int = 12) -> str:
    from ..params import HEIGHTS

    if (held := HEIGHTS[p.scheme]) is not None:
        return str(held)
    return "CASE " + " ".join(f"WHEN {n} <= {t} THEN {h}" for h, t in enumerate(p.thresholds()[:top])) + f" ELSE {top} END"


def fixed_spans(contents: str, p: StoreParams, top: int, x: str = "") -> str:
    """CTEs c{x} (content_id, version, body, n, h) and n{x} (content_id, version, level, s, e, ps) of whole, fixed and fixed_tree."""
    lengths = ", ".join(str(p.fixed_length(k)) for k in range(max(1, top)))
    return f"""c{x} AS MATERIALIZED (SELECT content_id, version, body, octet_length(body) AS n, {height("octet_length(body)", p)} AS h FROM ({contents})),
n{x} AS (
  SELECT content_id, version, h AS level, CAST(0 AS BIGINT) AS s, CAST(n AS BIGINT) AS e, CAST(-1 AS BIGINT) AS ps FROM c{x}
  UNION ALL
  SELECT content_id, version, level - 1, v, least(v + [{lengths}][level], e), s FROM n{x}, unnest(range(s, e, [{lengths}][level])) u(v) WHERE level > 0)"""


def cdc_spans(contents: str, p: StoreParams, top: int, x: str = "") -> str:
    """The same CTEs of cdc and cdc_tree in the prime ring, with windows that a node's start cuts short; single-level trees have top 1."""
    m, w = rolling.M31, p.window
    inv = pow(rolling.BASE31, -1, m)
    bits = 24

    steps = [f"""pw{x} AS MATERIALIZED (SELECT i, d, d2 FROM (SELECT i, CAST({_product(inv, "i", bits, m)} AS BIGINT) AS d, CAST({_product(rolling.BASE31, "(i + 1)", bits, m)} AS BIGINT) AS d2 FROM (SELECT unnest(range((SELECT max(octet_length(body)) FROM ({contents})))) AS i)))"""]
    steps.insert(0, f"""c{x} AS MATERIALIZED (SELECT content_id, version, body, octet_length(body) AS n, {height("octet_length(body)", p)} AS h FROM ({contents}))""")
    steps.append(f"""bt{x} AS MATERIALIZED (SELECT content_id, version, h, i, d2, CAST(sum((v + 1) * d % {m}) OVER (PARTITION BY content_id, version ORDER BY i) AS BIGINT) AS ps FROM (
  SELECT content_id, version, h, i, CAST('0x' || hx[2 * j + 1:2 * j + 2] AS BIGINT) AS v, d, d2 FROM (
    SELECT content_id, version, h, 128 * k + j AS i, j, hx FROM (
      SELECT content_id, version, h, k, hex(body[128 * k + 1:128 * k + 128]) AS hx FROM (SELECT content_id, version, h, body, unnest(range((n + 127) // 128)) AS k FROM c{x} WHERE n > 0)),
    unnest(range(length(hx) // 2)) AS q(j)) JOIN pw{x} USING (i)))""")
    # st: start of the node of the level above at each byte; a window reaches back w bytes, or to that start
    prior = f"SELECT content_id, version, h, i, d2, ps, CAST(0 AS BIGINT) AS st FROM bt{x}"
    unions = [f"SELECT content_id, version, h AS level, CAST(0 AS BIGINT) AS s, CAST(n AS BIGINT) AS e, CAST(-1 AS BIGINT) AS ps FROM c{x}"]
    for level in range(top - 1, -1, -1):
        limit = rolling.threshold(p, level)
        steps.append(f"""f{x}_{level} AS MATERIALIZED (SELECT a.content_id, a.version, a.h, a.i, a.d2, a.ps, a.st,
    a.h > {level} AND ((a.ps - coalesce(b.ps, 0)) % {m}) * a.d2 % {m} < {limit} AS hit
  FROM ({prior}) a LEFT JOIN bt{x} b ON b.content_id = a.content_id AND b.version = a.version AND b.i = greatest(a.i - {w}, a.st - 1))""")
        steps.append(f"""g{x}_{level} AS MATERIALIZED (SELECT content_id, version, h, i, d2, ps, st AS up,
    greatest(st, coalesce(max(CASE WHEN hit THEN i + 1 END) OVER (PARTITION BY content_id, version ORDER BY i ROWS BETWEEN UNBOUNDED PRECEDING AND 1 PRECEDING), 0)) AS st FROM f{x}_{level})""")
        prior = f"SELECT content_id, version, h, i, d2, ps, st FROM g{x}_{level}"
        unions.append(f"SELECT content_id, version, {level} AS level, CAST(st AS BIGINT) AS s, CAST(max(i) + 1 AS BIGINT) AS e, CAST(min(up) AS BIGINT) AS ps FROM g{x}_{level} WHERE h > {level} GROUP BY content_id, version, st")
    steps.append(f"n{x} AS MATERIALIZED (" + " UNION ALL ".join(unions) + ")")
    return ",\n".join(steps)


def _product(base: int, e: str, bits: int, m: int) -> str:
    """base^e modulo m, as a product over the bits of e."""
    out = f"CASE WHEN {e} & 1 = 1 THEN CAST({base % m} AS BIGINT) ELSE CAST(1 AS BIGINT) END"
    for k in range(1, bits):
        out = f"(({out}) * CASE WHEN ({e} >> {k}) & 1 = 1 THEN CAST({pow(base, 1 << k, m)} AS BIGINT) ELSE CAST(1 AS BIGINT) END % {m})"
    return out


def spans(contents: str, p: StoreParams, top: int, x: str = "") -> str:
    return cdc_spans(contents, p, top, x) if p.scheme.startswith("cdc") else fixed_spans(contents, p, top, x)


def keyed(contents: str, p: StoreParams, top: int, x: str = "") -> str:
    """CTEs up to k{x}: content_id, version, level, s, e, ps, size, children, key (hex), for all nodes."""
    top = {"whole": 0, "fixed": 1, "cdc": 1}.get(p.scheme, top)
    out = [spans(contents, p, top, x)]
    # leaves are cut from blocks that overlap, as a slice of a long body costs its whole length
    whole = p.scheme == "whole"
    out.append(f"""bl{x} AS MATERIALIZED (SELECT content_id, version, k, {"body" if whole else "body[65536 * k + 1:65536 * k + 131072]"} AS part FROM c{x}, unnest(range({1 if whole else "n // 65536 + 1"})) AS q(k))""")
    out.append(f"""k{x}_0 AS MATERIALIZED (SELECT n.content_id, n.version, n.level, n.s, n.e, n.ps, n.e - n.s AS size, 0 AS children, {tag("c.part[n.s - 65536 * c.k + 1:n.e - 65536 * c.k]", p)} AS key
  FROM n{x} n JOIN bl{x} c ON n.content_id = c.content_id AND n.version = c.version AND c.k = {0 if whole else "n.s // 65536"} WHERE n.level = 0)""")
    for level in range(1, top + 1):
        out.append(f"""k{x}_{level} AS MATERIALIZED (SELECT n.content_id, n.version, n.level, n.s, n.e, n.ps, octet_length(unhex(coalesce(l.keys, ''))) AS size, coalesce(l.children, 0) AS children, {tag("unhex(coalesce(l.keys, ''))", p)} AS key
  FROM n{x} n LEFT JOIN (SELECT content_id, version, ps, string_agg(key, '' ORDER BY s) AS keys, count(*) AS children FROM k{x}_{level - 1} GROUP BY content_id, version, ps) l
  ON l.content_id = n.content_id AND l.version = n.version AND l.ps = n.s WHERE n.level = {level})""")
    out.append(f"k{x} AS MATERIALIZED (" + " UNION ALL ".join(f"SELECT * FROM k{x}_{level}" for level in range(top + 1)) + ")")
    return ",\n".join(out)


def with_(*parts: str) -> str:
    return "WITH RECURSIVE " + ",\n".join(parts) + "\n"


def grid(contents: str, params: list[StoreParams], tops: dict[int, int]) -> tuple[str, str]:
    """(CTEs, name of one with scheme, s, content_id, version, key, size over all parameter sets)."""
    parts, rows = [], []
    for k, p in enumerate(params):
        parts.append(keyed(contents, p, tops.get(p.chunk, 1), f"_{k}"))
        rows.append(f"SELECT '{p.scheme}' AS scheme, {p.chunk} AS s, content_id, version, key, size FROM k_{k}")
    parts.append("grid AS MATERIALIZED (" + " UNION ALL ".join(rows) + ")")
    return with_(*parts), "grid"
