"""The registered queries' meaning in SQL of another engine, composed from shared CTEs."""

from __future__ import annotations

from ..operators.oblivious import Selection, uniform_clamped
from ..operators.params import Params

ELL = 21


def string_id(x: str) -> str:
    return f"('0x' || substr(md5({x}), 1, 15))::BIGINT"


LINE_KEY = "l_orderkey, l_linenumber, l_partkey, l_suppkey, round(l_extendedprice * 100)::BIGINT, date_diff('day', DATE '1970-01-01', l_shipdate::DATE), round(l_discount * 100)::BIGINT, round(l_tax * 100)::BIGINT, l_quantity::BIGINT"
LINE_ID = f"concat_ws('|', {LINE_KEY})"
_FLOW = "CASE WHEN l_returnflag = 'R' THEN 2 * l_partkey + 1 ELSE 2 * l_suppkey END AS u, CASE WHEN l_returnflag = 'R' THEN 2 * l_suppkey ELSE 2 * l_partkey + 1 END AS v"
_NATIONS = "lineitem JOIN orders ON l_orderkey = o_orderkey JOIN customer ON o_custkey = c_custkey JOIN supplier ON l_suppkey = s_suppkey"

EDGES = {
    "goods_flow": f"SELECT {LINE_ID} AS eid, {_FLOW} FROM lineitem",
    "ship_bipartite": f"SELECT {LINE_ID} AS eid, 2 * l_suppkey AS u, 2 * l_partkey + 1 AS v FROM lineitem",
    "nation_trade": f"SELECT {LINE_ID} AS eid, s_nationkey::BIGINT AS u, c_nationkey::BIGINT AS v FROM {_NATIONS}",
    "region_trade": f"SELECT {LINE_ID} AS eid, a.n_regionkey::BIGINT AS u, b.n_regionkey::BIGINT AS v FROM {_NATIONS} JOIN nation a ON s_nationkey = a.n_nationkey JOIN nation b ON c_nationkey = b.n_nationkey",
    "event_next": f"SELECT event_id::VARCHAR AS eid, {string_id('event_type')} AS u, {string_id('nxt')} AS v FROM (SELECT event_id, event_type, lead(event_type) OVER (PARTITION BY user_id ORDER BY ts, event_id) AS nxt FROM events) WHERE nxt IS NOT NULL",
    "user_next": "SELECT event_id::VARCHAR AS eid, user_id AS u, nxt AS v FROM (SELECT event_id, user_id, lead(user_id) OVER (ORDER BY ts, event_id) AS nxt FROM events) WHERE nxt IS NOT NULL",
    "user_item": "SELECT event_id::VARCHAR AS eid, CASE WHEN buys THEN 2 * user_id ELSE item END AS u, CASE WHEN buys THEN item ELSE 2 * user_id END AS v, ts FROM (SELECT event_id, ts, user_id, event_type IN ('click', 'purchase') AS buys, 2 * json_extract_string(props, '$.k')::BIGINT + 1 AS item FROM events)",
    "part_pair": "SELECT concat_ws('|', k1, k2) AS eid, p1 AS u, p2 AS v FROM (SELECT l_orderkey, l_partkey AS p1, " + LINE_ID.replace("'|'", "','", 1) + " AS k1 FROM lineitem) JOIN (SELECT l_orderkey AS ok, l_partkey AS p2, " + LINE_ID.replace("'|'", "','", 1) + " AS k2 FROM lineitem) ON l_orderkey = ok WHERE p1 < p2",
    "customer_star": "SELECT c_custkey::VARCHAR AS eid, 2 * c_custkey AS u, (2 * c_nationkey + 1)::BIGINT AS v FROM customer",
    "embed_knn": "SELECT concat_ws('|', vec_id, other) AS eid, vec_id AS u, other AS v FROM (SELECT x.vec_id, y.vec_id AS other, row_number() OVER (PARTITION BY x.vec_id ORDER BY list_cosine_similarity(x.embedding::DOUBLE[], y.embedding::DOUBLE[]) DESC, y.vec_id) AS r FROM embeddings x JOIN embeddings y ON x.vec_id <> y.vec_id) WHERE r <= 8",
    "turn_roles": f"SELECT concat_ws('|', conv_id, turn) AS eid, {string_id('role')} AS u, {string_id('nxt')} AS v FROM (SELECT conv_id, turn, role, lead(role) OVER (PARTITION BY conv_id ORDER BY turn) AS nxt FROM conversations) WHERE nxt IS NOT NULL",
    "doc_lang": f"SELECT doc_id::VARCHAR AS eid, CASE WHEN good THEN s ELSE g END AS u, CASE WHEN good THEN g ELSE s END AS v FROM (SELECT d.doc_id, coalesce(quality = 1, false) AS good, {string_id(chr(39) + 's:' + chr(39) + ' || source')} AS s, {string_id(chr(39) + 'l:' + chr(39) + ' || lang')} AS g FROM documents d JOIN labels b ON d.doc_id = b.doc_id WHERE source IS NOT NULL AND lang IS NOT NULL)",
    "page_nav": f"SELECT concat_ws('|', page_id, n) AS eid, {string_id(chr(39) + 'h:' + chr(39) + ' || host')} AS u, {string_id(chr(39) + 't:' + chr(39) + ' || target')} AS v FROM (SELECT page_id, host, unnest(range(len(ts))) AS n, unnest(ts) AS target FROM (SELECT page_id, regexp_extract(url, '^[a-z]+://([^/]+)', 1) AS host, regexp_extract_all(html, 'href=\"/([^\"]*)\"', 1) AS ts FROM pages))",
    "bench_overlap": "SELECT concat_ws('|', doc_id, item_id) AS eid, 2 * doc_id AS u, 2 * item_id + 1 AS v FROM (SELECT DISTINCT doc_id, item_id FROM (SELECT doc_id, array_to_string(w[i:i + 7], ' ') AS g FROM (SELECT doc_id, w, unnest(range(1, len(w) - 6)) AS i FROM (SELECT doc_id, string_split(text, ' ') AS w FROM documents))) JOIN (SELECT item_id, array_to_string(w[i:i + 7], ' ') AS g FROM (SELECT item_id, w, unnest(range(1, len(w) - 6)) AS i FROM (SELECT item_id, string_split(text, ' ') AS w FROM benchmark))) USING (g))",
    "order_chain": "SELECT o_orderkey::VARCHAR AS eid, o_custkey AS u, nxt AS v FROM (SELECT o_orderkey, o_custkey, lead(o_custkey) OVER (ORDER BY o_orderdate, o_orderkey) AS nxt FROM orders) WHERE nxt IS NOT NULL",
}


def edges(name: str, alias: str = "e") -> str:
    return f"{alias} AS (SELECT * FROM ({EDGES[name]}) WHERE u <> v)"


def stats(of: str = "e", alias: str = "st", weight: str = "1") -> str:
    return f"{alias} AS (SELECT vid, sum(o)::BIGINT AS d_out, sum(i)::BIGINT AS d_in, sum(o + i)::BIGINT AS deg FROM (SELECT u AS vid, {weight} AS o, 0 AS i FROM {of} UNION ALL SELECT v, 0, {weight} FROM {of}) GROUP BY vid)"


def bias_class(ell: int = ELL, o: str = "d_out", d: str = "deg") -> str:
    return f"least({ell}, ({o} * {ell}) // {d} + 1)::INT"


def classes(of: str = "st", alias: str = "cl", ell: int = ELL, k: int = 24) -> str:
    return f"{alias} AS (SELECT vid, d_out, deg, {bias_class(ell)} AS i, least(length(bin(deg)), {k})::INT AS a FROM {of})"


def graph(name: str, ell: int = ELL, k: int = 24) -> str:
    return f"WITH {edges(name)}, {stats()}, {classes(ell=ell, k=k)}"


def cells(of: str = "e", cl: str = "cl", alias: str = "sn") -> str:
    return f"{alias} AS (SELECT s.i, t.i AS j, count(*)::BIGINT AS weight FROM {of} JOIN {cl} s ON u = s.vid JOIN {cl} t ON v = t.vid GROUP BY 1, 2)"


def refined(alias: str = "rf") -> str:
    return f"{alias} AS (SELECT s.a, t.a AS b, s.i, t.i AS j, count(*)::BIGINT AS weight FROM e JOIN cl s ON u = s.vid JOIN cl t ON v = t.vid GROUP BY 1, 2, 3, 4)"


def size(i: str, w: int, n: int) -> str:
    return f"(least({i} + {w}, {n}) - greatest({i} - {w}, 1) + 1)"


def extreme(i: str, w: int, n: int, pick: str) -> str:
    near = [f"greatest({i} - 1, 1)", i, f"least({i} + 1, {n})"]
    return f"{pick}({', '.join(size(x, w, n) for x in near)})"


def spread(of: str, axes: list[tuple[str, int]], w: int, radius: int, factor: str = "plain") -> str:
    """Cells of ``of`` (axes..., x) scattered over their windows."""
    f = {"plain": lambda c, n: size(c, w, n), "lo": lambda c, n: extreme(c, w, n, "greatest"), "hi": lambda c, n: extreme(c, w, n, "least")}[factor]
    share = " * ".join(f"(1.0::DOUBLE / {f(c, n)})" for c, n in axes)
    wins = " ".join(f", LATERAL (SELECT unnest(range(greatest({of}.{c} - {radius}, 1), least({of}.{c} + {radius}, {n}) + 1)) AS n{c}) AS l{c}" for c, n in axes)
    return f"SELECT {', '.join(f'n{c}::INT AS {c}' for c, _ in axes)}, sum(x * {share}) AS x FROM {of}{wins} GROUP BY {', '.join(f'n{c}' for c, _ in axes)}"


def rule_sums(of: str = "sn", sel: Selection | None = None) -> str:
    """num and m of a rule with fractions over cells (i, j, weight)."""
    sel = sel or uniform_clamped(ELL)
    r = "[" + ", ".join(map(str, sel.num)) + "]"
    return f"SELECT sum(weight * {r}[i] * ({sel.den} - {r}[j]))::BIGINT AS num, sum(weight)::BIGINT AS m FROM {of}"


def rule_value(of: str = "sn", sel: Selection | None = None) -> str:
    sel = sel or uniform_clamped(ELL)
    return f"SELECT num, m, num / (m * {sel.den**2})::DOUBLE AS value FROM ({rule_sums(of, sel)})"


ZEROTH = "CASE WHEN 3 * net >= 2 * m THEN net / (2 * m)::DOUBLE ELSE 0.25 + (net * net)::DOUBLE / (16 * m * (m - net))::DOUBLE END"


def word(parts: str) -> str:
    return f"('0x' || substr(md5({parts}), 1, 8))::BIGINT::DOUBLE"


def poly(x: str) -> str:
    v = f"({x} % 2147483647)"
    return f"((((c3 * {v} + c2) % 2147483647) * {v} + c1) % 2147483647 * {v} + c0) % 2147483647"


def toss(p: Params) -> str:
    """The condition that an edge's coin falls in a layer: a word of the digest that four layers share,
    or of the one digest of all layers."""
    if p.mode == "nested":
        word_of = f"md5(concat_ws(':', e.eid, 'n', {p.seed}))"
        return f"par.q >= 1 OR ('0x' || substr({word_of}, 1, 8))::BIGINT::DOUBLE < par.q * 4294967296"
    return f"par.q >= 1 OR ('0x' || substr(md5(concat_ws(':', e.eid, (par.layer - 1) // 4, {p.seed})), 8 * ((par.layer - 1) % 4) + 1, 8))::BIGINT::DOUBLE < par.q * 4294967296"


def sketch(p: Params, name: str, source: str | None = None, pairs: str = "") -> str:
    """CTEs params, rw (sampled rows), tv (tracked), tr (trimmed), ap (apparent), us (usable)."""
    rows = ", ".join(f"({r[1]}, {r[2]!r}::DOUBLE, {', '.join(map(str, r[3:]))})" for r in p.rows())
    shift = "0" if p.force_q1 else f"greatest(layer - {p.k_star}, 0)"
    tracked = "ku AND kv" if p.store == "induced" else "ku OR kv"
    return f"""WITH {source or edges(name)}, par(layer, q, thr, c0, c1, c2, c3) AS (VALUES {rows}),
coined AS (SELECT e.eid, e.u, e.v, par.* FROM e JOIN par ON {toss(p)}),
rw AS (SELECT * FROM (SELECT layer, eid, u, v, {poly('u')} < thr AS ku, {poly('v')} < thr AS kv FROM coined) WHERE {tracked}),
ends AS (SELECT layer, u AS vid, 1 AS o, eid, u, v, ku, kv FROM rw WHERE ku UNION ALL SELECT layer, v, 0, eid, u, v, ku, kv FROM rw WHERE kv),
tv AS (SELECT DISTINCT layer, vid FROM ends),
tr AS (SELECT DISTINCT layer, eid, u, v, ku, kv FROM (SELECT *, row_number() OVER (PARTITION BY layer, vid ORDER BY {word(f"concat_ws(':', eid, 't:{p.seed}')")}, eid) AS rk FROM ends) WHERE rk <= {p.e_cap}),
kept AS (SELECT layer, u AS vid, 1 AS o FROM tr WHERE ku UNION ALL SELECT layer, v, 0 FROM tr WHERE kv),
ap AS (SELECT layer, vid, d_out, deg - d_out AS d_in, deg, least(length(bin(least(deg * (1::BIGINT << {shift}), {1 << p.k}))), {p.k})::INT AS a, {bias_class(p.ell)} AS i FROM (SELECT layer, vid, sum(o)::BIGINT AS d_out, count(*)::BIGINT AS deg FROM kept GROUP BY 1, 2)),
us AS (SELECT layer, vid, a, i FROM ap WHERE deg < {p.e_cap} AND abs(a - layer) <= {p.w}),
mm AS (SELECT count(*)::BIGINT AS m FROM e),
lp AS (SELECT s.layer AS la, t.layer AS lb, s.a AS a, t.a AS b, s.i AS i, t.i AS j, count(*)::BIGINT AS n FROM tr JOIN us s ON tr.u = s.vid AND s.layer >= tr.layer JOIN us t ON tr.v = t.vid AND t.layer >= tr.layer WHERE least(s.layer, t.layer) = tr.layer {pairs} GROUP BY 1, 2, 3, 4, 5, 6),
wt AS (SELECT la, lb, i, j, sum(n / ({size('a', p.w, p.k)} * {size('b', p.w, p.k)})::DOUBLE / (greatest(x.q, y.q) * x.pp * y.pp)) AS x0 FROM lp JOIN (SELECT layer, q, thr / 2147483647::DOUBLE AS pp FROM par) x ON la = x.layer JOIN (SELECT layer, q, thr / 2147483647::DOUBLE AS pp FROM par) y ON lb = y.layer GROUP BY 1, 2, 3, 4)"""
