"""SQL of the graphs and of the iterations, for comparison with the engine on the same tables."""

from __future__ import annotations

TAG = 1 << 40


def _text(x: str) -> str:
    return f"('0x' || substr(md5({x}), 1, 15))::BIGINT"


def _pairs(body: str, loops: bool = False) -> str:
    keep = "" if loops else " AND src <> dst"
    return f"SELECT DISTINCT src, dst, 1.0::DOUBLE AS w FROM ({body}) WHERE src IS NOT NULL AND dst IS NOT NULL{keep}"


def _both(body: str) -> str:
    return f"SELECT src, dst, min(w) AS w FROM (SELECT src, dst, w FROM ({body}) UNION ALL SELECT dst, src, w FROM ({body})) GROUP BY src, dst"


EDGES = {
    "trade": """SELECT src, dst, sum(w) AS w FROM (
        SELECT s_nationkey::BIGINT AS src, c_nationkey::BIGINT AS dst, l_extendedprice * (1 - l_discount) AS w
        FROM lineitem JOIN orders ON l_orderkey = o_orderkey JOIN customer ON o_custkey = c_custkey
        JOIN supplier ON l_suppkey = s_suppkey) GROUP BY src, dst""",
    "user_trans": _pairs("SELECT user_id AS src, lead(user_id) OVER (ORDER BY ts, event_id) AS dst FROM events"),
    "part_chain": _pairs(
        "SELECT l_partkey AS src, lead(l_partkey) OVER (PARTITION BY l_orderkey"
        " ORDER BY l_linenumber, l_partkey, l_suppkey, l_extendedprice) AS dst FROM lineitem"
    ),
    "supply_sym": _both(_pairs(f"SELECT {TAG} + l_suppkey AS src, {2 * TAG} + l_partkey AS dst FROM lineitem")),
    "cust_part_sym": _both(
        _pairs(f"SELECT {3 * TAG} + o_custkey AS src, {2 * TAG} + l_partkey AS dst FROM lineitem JOIN orders ON l_orderkey = o_orderkey")
    ),
    "word_bigram": _pairs(
        f"SELECT {_text('t[i]')} AS src, {_text('t[i + 1]')} AS dst FROM (SELECT t, unnest(range(1, len(t))) AS i FROM"
        " (SELECT regexp_extract_all(lower(text), '([a-zà-ÿ]+)', 1) AS t FROM documents))"
    ),
    "weblink": _pairs(
        f"SELECT page_id AS src, {_text('path')} AS dst FROM"
        " (SELECT page_id, unnest(regexp_extract_all(html, 'href=\"([^\"]*)\"', 1)) AS path FROM pages)"
    ),
    "fk_forest": _pairs(
        f"SELECT {TAG} + n_regionkey AS src, {2 * TAG} + n_nationkey AS dst FROM nation"
        f" UNION ALL SELECT {2 * TAG} + c_nationkey, {3 * TAG} + c_custkey FROM customer"
        f" UNION ALL SELECT {3 * TAG} + o_custkey, {4 * TAG} + o_orderkey FROM orders"
    ),
    "conv_chain": _pairs(
        f"SELECT conv_id * {1 << 20} + turn AS src,"
        f" conv_id * {1 << 20} + lead(turn) OVER (PARTITION BY conv_id ORDER BY turn) AS dst FROM conversations"
    ),
    "doc_dup": _pairs(
        "SELECT doc_id AS src, min(doc_id) OVER (PARTITION BY md5(regexp_replace(lower(text), '\\s+', ' ', 'g'))) AS dst FROM documents"
    ),
    "doc_line": _pairs(
        "SELECT doc_id AS src, min(doc_id) OVER (PARTITION BY md5(line)) AS dst FROM"
        " (SELECT doc_id, unnest(string_split(text, chr(10))) AS line FROM documents) WHERE length(line) >= 40"
    ),
}
EDGES["weblink_sym"] = _both(EDGES["weblink"])


def graph(name: str, extra_vertices: str = "") -> str:
    """CTEs e (src, dst, w) and v (node), without the leading WITH."""
    more = f" UNION {extra_vertices}" if extra_vertices else ""
    return f"e AS MATERIALIZED ({EDGES[name]}), v AS MATERIALIZED (SELECT src AS node FROM e UNION SELECT dst FROM e{more})"


def chain(head: str, start: str, step: str, rounds: int, out: str) -> str:
    """head: CTEs; start: select (node, val); step: select with {old} as the previous table; out: select with {last}."""
    parts = [head, f"r0 AS MATERIALIZED ({start})"]
    parts += [f"r{k} AS MATERIALIZED ({step.format(old=f'r{k - 1}')})" for k in range(1, rounds + 1)]
    return "WITH " + ", ".join(parts) + " " + out.format(last=f"r{rounds}")


SHARES = "d AS (SELECT src AS s, count(*)::DOUBLE AS t FROM e GROUP BY src), m AS MATERIALIZED (SELECT src, dst, 1.0::DOUBLE / t AS w FROM e JOIN d ON src = s)"
WEIGHTED = "d AS (SELECT src AS s, sum(w) AS t FROM e GROUP BY src), m AS MATERIALIZED (SELECT src, dst, w / t AS w FROM e JOIN d ON src = s)"
COUNT = "c AS (SELECT count(*)::DOUBLE AS n FROM v)"
FOLDED = "LEFT JOIN (SELECT dst, {fold} AS acc FROM m JOIN {{old}} o ON m.src = o.node GROUP BY dst) a ON x.node = a.dst"


def pagerank(name: str, rounds: int, digits: int, damping: float = 0.85, weighted: bool = False, uniform: bool = False) -> str:
    acc = FOLDED.format(fold="sum(m.w * o.val)")
    base = f"(1 - {damping}::DOUBLE) / n"
    if uniform:
        base += f" + {damping}::DOUBLE * (SELECT coalesce(sum(val), 0) FROM {{old}} WHERE node NOT IN (SELECT src FROM e)) / n"
    step = f"SELECT x.node, {base} + {damping}::DOUBLE * coalesce(acc, 0) AS val FROM {{old}} x CROSS JOIN c {acc}"
    head = ", ".join([graph(name), WEIGHTED if weighted else SHARES, COUNT])
    return chain(head, "SELECT node, 1 / n AS val FROM v CROSS JOIN c", step, rounds, f"SELECT node, round(val, {digits}) AS rank FROM {{last}}")


def block(psi: str, node: str, b: int) -> str:
    return {
        "mod": f"({node} % {b})",
        "mult": f"((({node} % 4294967296)::HUGEINT * 2654435761 % 4294967296) % {b})",
        "md5": f"(('0x' || substr(md5(({node})::VARCHAR), 1, 8))::BIGINT % {b})",
    }[psi]


DEGREES = (
    "g AS MATERIALIZED (SELECT v.node, coalesce(o.k, 0) AS out_degree, coalesce(i.k, 0) AS in_degree FROM v"
    " LEFT JOIN (SELECT src, count(*) AS k FROM e GROUP BY src) o ON v.node = o.src"
    " LEFT JOIN (SELECT dst, count(*) AS k FROM e GROUP BY dst) i ON v.node = i.dst)"
)


def summary(name: str) -> str:
    return (
        f"WITH {graph(name)}, {DEGREES} SELECT count(*) AS n, sum(out_degree)::BIGINT AS m,"
        " round(sum(out_degree) / (count(*)::DOUBLE * count(*)), 12) AS density, round(sum(out_degree) / count(*)::DOUBLE, 9) AS average,"
        " max(out_degree)::BIGINT AS max_out, max(in_degree)::BIGINT AS max_in, count(*) FILTER (out_degree = 0) AS dangling,"
        " count(*) FILTER (in_degree = 0) AS no_in FROM g"
    )


def histogram(name: str) -> str:
    return (
        f"WITH {graph(name)}, {DEGREES} SELECT 'in' AS kind, in_degree::BIGINT AS degree, count(*) AS n FROM g GROUP BY 2"
        " UNION ALL SELECT 'out', out_degree::BIGINT, count(*) FROM g GROUP BY 2"
    )


def blocks(name: str, psi: str, b: int, theta: int | None) -> str:
    heavy = "0" if theta is None else f"(k >= {theta})::INT"
    return (
        f"WITH {graph(name)}, d AS (SELECT src AS s, count(*) AS k FROM e GROUP BY src),"
        f" x AS (SELECT {block(psi, 'dst', b)}::INT AS rb, {block(psi, 'src', b)}::INT AS cb, dst, {heavy} AS h FROM e JOIN d ON src = s)"
        " SELECT rb, cb, count(*) AS edges, count(DISTINCT dst) AS rows, (count(*) - sum(h))::BIGINT AS light, sum(h)::BIGINT AS heavy FROM x GROUP BY rb, cb"
    )


def measured(name: str, psi: str, b: int, theta: int | None) -> str:
    """Elements of one iteration: b, read, written, exchanged, diagonal, total."""
    light = "true" if theta is None else f"coalesce(k, 0) < {theta}"
    return (
        f"WITH {graph(name)}, d AS (SELECT src AS s, count(*) AS k FROM e GROUP BY src),"
        f" n AS (SELECT count(*) FILTER ({light}) AS ns, count(*) FILTER (NOT ({light})) AS nd FROM v LEFT JOIN d ON node = s),"
        f" p AS (SELECT DISTINCT {block(psi, 'src', b)} AS cb, dst, {block(psi, 'dst', b)} AS rb FROM e JOIN d ON src = s WHERE {light}),"
        " u AS (SELECT count(*) FILTER (cb <> rb) AS off, count(*) FILTER (cb = rb) AS own FROM p)"
        f" SELECT {b}::INT AS b, ns + {b} * nd AS read, ns + nd AS written, 2 * off AS exchanged, own AS diagonal,"
        f" ns + {b} * nd + ns + nd + 2 * off AS total FROM n, u"
    )


def costs(name: str, bs: tuple[int, ...]) -> str:
    values = ", ".join(f"({b})" for b in bs)
    return (
        f"WITH {graph(name)}, s AS (SELECT (SELECT count(*) FROM v)::DOUBLE AS n, (SELECT count(*) FROM e)::DOUBLE AS m),"
        f" q AS (SELECT b, n, m, power(1 - m / (n * n), n / b) AS stay FROM s, (VALUES {values}) t(b))"
        " SELECT b::INT AS b, round(stay, 9) AS stay, round((b + 1) * n, 3) AS c_h, round(2 * n * (1 + (b - 1) * (1 - stay)), 3) AS c_v,"
        " CASE WHEN stay < 0.5 THEN 'horizontal' ELSE 'vertical' END AS choice FROM q"
    )


def thetas(name: str, b: int, candidates: tuple[int | None, ...]) -> str:
    values = ", ".join(f"({'NULL' if t is None else t})" for t in candidates)
    return f"""
        WITH {graph(name)}, {DEGREES}, t AS (SELECT th::BIGINT AS theta FROM (VALUES {values}) q(th)), n AS (SELECT count(*)::DOUBLE AS n FROM v),
        p AS (SELECT theta, sum((theta IS NULL OR out_degree < theta)::INT) / count(*)::DOUBLE AS p_vertex,
              sum(CASE WHEN theta IS NULL OR out_degree < theta THEN out_degree ELSE 0 END) / sum(out_degree)::DOUBLE AS p_edge
              FROM t, g GROUP BY theta),
        i AS (SELECT in_degree AS d, count(*) AS k FROM g GROUP BY in_degree),
        f AS (SELECT theta, p_vertex, p_edge, sum((1 - power(1 - p_vertex / {b}, d)) * k) AS fv, sum((1 - power(1 - p_edge / {b}, d)) * k) AS fe
              FROM p, i GROUP BY theta, p_vertex, p_edge),
        r AS (SELECT theta, dst, count(*) FILTER (theta IS NULL OR out_degree < theta) AS light FROM t, e JOIN g ON e.src = g.node GROUP BY theta, dst),
        u AS (SELECT theta, sum(1 - power(1 - 1.0::DOUBLE / {b}, light)) AS u FROM r GROUP BY theta)
        SELECT f.theta, round(p_vertex, 9) AS p_vertex, round(p_edge, 9) AS p_edge,
          round(n * (p_vertex + {b} * (1 - p_vertex) + 1) + 2 * ({b} - 1) * fv, 3) AS cost_vertex_share,
          round(n * (p_vertex + {b} * (1 - p_vertex) + 1) + 2 * ({b} - 1) * fe, 3) AS cost_edge_share,
          round(n * (p_vertex + {b} * (1 - p_vertex) + 1) + 2 * ({b} - 1) * u, 3) AS cost_row_conditional
        FROM f JOIN u ON f.theta IS NOT DISTINCT FROM u.theta, n"""


def components(name: str, symmetric: bool = False) -> str:
    both = "SELECT src, dst FROM e" + ("" if symmetric else " UNION SELECT dst, src FROM e")
    return (
        f"WITH RECURSIVE {graph(name)}, s AS MATERIALIZED ({both}),"
        " r AS (SELECT node, node AS label FROM v UNION SELECT s.dst, r.label FROM r JOIN s ON r.node = s.src)"
        " SELECT node, min(label) AS component FROM r GROUP BY node"
    )


def hops(name: str, source: str, depth: int) -> str:
    """Levels from one vertex; null where there is no path of at most ``depth`` edges."""
    return (
        f"WITH RECURSIVE {graph(name)}, r AS (SELECT ({source})::BIGINT AS node, 0 AS k UNION"
        f" SELECT e.dst, r.k + 1 FROM r JOIN e ON r.node = e.src WHERE r.k < {depth})"
        " SELECT v.node, l.k::BIGINT AS level FROM v LEFT JOIN (SELECT node, min(k) AS k FROM r GROUP BY node) l ON v.node = l.node"
    )


def fraction_of(name: str, f: float) -> str:
    """CTEs e, v of the subgraph that a vertex sample induces, without the leading WITH."""
    keep = lambda x: f"('0x' || substr(md5({x}::VARCHAR), 1, 8))::BIGINT < floor({f}::DOUBLE * 4294967296)"
    return (
        f"e0 AS MATERIALIZED ({EDGES[name]}), e AS MATERIALIZED (SELECT * FROM e0 WHERE {keep('src')} AND {keep('dst')}),"
        " v AS MATERIALIZED (SELECT src AS node FROM e UNION SELECT dst FROM e)"
    )


def placements(theta: int | None, b: str = "b") -> str:
    """CTEs that count, for the blocks of md5 in table bb (b): n, m; heavy vertices; partial results; the largest block."""
    light = "true" if theta is None else f"coalesce(k, 0) < {theta}"
    p, q = block("md5", "src", b), block("md5", "dst", b)
    return (
        "c AS MATERIALIZED (SELECT (SELECT count(*) FROM v) AS n, (SELECT count(*) FROM e) AS m), d AS MATERIALIZED (SELECT src AS s, count(*) AS k FROM e GROUP BY src),"
        f" h AS MATERIALIZED (SELECT count(*) FILTER ({light}) AS ns, count(*) FILTER (NOT ({light})) AS nd FROM v LEFT JOIN d ON node = s),"
        f" pv AS MATERIALIZED (SELECT count(*) FILTER (cb <> rb) AS off FROM (SELECT DISTINCT {p} AS cb, {q} AS rb, dst FROM e, bb)),"
        f" ph AS MATERIALIZED (SELECT count(*) FILTER (cb <> rb) AS off FROM (SELECT DISTINCT {p} AS cb, {q} AS rb, dst FROM e JOIN d ON src = s, bb WHERE {light})),"
        f" mb AS MATERIALIZED (SELECT max(x) AS x FROM (SELECT count(*) AS x FROM v, bb GROUP BY {block('md5', 'node', b)}))"
    )


def growing(name: str, fractions: tuple[float, ...], workers: int, budget: int, theta: int, element: int = 16, cell: int = 24) -> str:
    """What each method holds and moves on growing subgraphs, and whether it fits: fraction, edges, method, status,
    held_bytes, elements."""
    grid = max(2, round(workers**0.5))
    part = f"{block('md5', 'src', grid)} * {grid} + {block('md5', 'dst', grid)}"
    w = lambda x: block("md5", x, workers)
    one = (
        "SELECT * FROM (WITH {cut}, bb AS (SELECT CASE WHEN 2.0::DOUBLE * count(*) / {most} < {workers} THEN {workers} ELSE ceil(2.0::DOUBLE * count(*) / {most})::BIGINT END AS b FROM v), {counts},"
        " l AS (SELECT greatest(0, {most} - 2 * x) AS hashed FROM mb),"
        " pw AS (SELECT count(*) FILTER (cb <> rb) AS off, count(*) AS all_ FROM (SELECT DISTINCT {wsrc} AS cb, {wdst} AS rb, dst FROM e)),"
        " cut AS MATERIALIZED (SELECT src, dst, {part} AS part FROM e),"
        " mi AS (SELECT (SELECT count(*) FROM (SELECT DISTINCT part, src FROM cut)) + (SELECT count(*) FROM (SELECT DISTINCT part, dst FROM cut)) AS copies),"
        " vm AS (SELECT max(x) AS x FROM (SELECT count(*) * {cell} + (count(DISTINCT src) + count(DISTINCT dst)) * {element} AS x FROM cut GROUP BY part)),"
        " wc AS (SELECT max(x) AS x FROM (SELECT p, sum(x) AS x FROM (SELECT {wnode} AS p, count(*) * 2 * {element} AS x FROM v GROUP BY 1"
        " UNION ALL SELECT {wsrc}, count(*) * {cell} FROM e GROUP BY 1 UNION ALL SELECT p, count(*) * {element} FROM (SELECT DISTINCT {wsrc} AS p, dst FROM e) GROUP BY 1) GROUP BY p)),"
        " s AS (SELECT CASE WHEN power(1 - m::DOUBLE / (n::DOUBLE * n), n::DOUBLE / b) < 0.5 THEN 'horizontal' ELSE 'vertical' END AS choice FROM c, bb),"
        " x AS (SELECT 'horizontal' AS method, {element} * (2 * x + CASE WHEN n <= hashed THEN n ELSE 0 END) AS held, b * n + n AS total FROM mb, c, bb, l"
        " UNION ALL SELECT 'vertical', {element} * 2 * x, 2 * n + 2 * off FROM mb, c, pv"
        " UNION ALL SELECT 'hybrid', {element} * (2 * x + CASE WHEN nd <= hashed THEN nd ELSE 0 END), ns + b * nd + n + 2 * off FROM mb, c, bb, l, h, ph"
        " UNION ALL SELECT 'reshuffle', {cell}, m + 2 * n + 2 * (m + n + off) FROM c, pw"
        " UNION ALL SELECT 'vertex_cut', {cell}, 2 * n + 2 * copies FROM c, mi"
        " UNION ALL SELECT 'vertex_cut_memory', x, 2 * n + 2 * copies FROM c, mi, vm"
        " UNION ALL SELECT 'vertex_centric', x, 2 * n + 2 * off FROM c, pw, wc),"
        " y AS (SELECT * FROM x UNION ALL SELECT 'selected', held, total FROM x JOIN s ON method = choice)"
        " SELECT {f}::DOUBLE AS fraction, m AS edges, method, CASE WHEN held > {budget} THEN 'o.o.m.' ELSE 'done' END AS status, held::BIGINT AS held_bytes,"
        " CASE WHEN held > {budget} THEN 0 ELSE total END::BIGINT AS elements FROM y, c)"
    )
    return " UNION ALL ".join(
        one.format(
            cut=fraction_of(name, f), most=budget // element, workers=workers, counts=placements(theta), wsrc=w("src"), wdst=w("dst"), wnode=w("node"), part=part, cell=cell, element=element, budget=budget, f=f
        )
        for f in fractions
    )


def densities(names: tuple[str, ...], bs: tuple[int, ...], candidates: tuple[int | None, ...]) -> str:
    """Elements of the four placements, the hybrid at the threshold of least row-conditional cost."""
    rows = []
    for g in names:
        for b in bs:
            rows.append(
                f"SELECT * FROM (WITH {graph(g)}, th AS MATERIALIZED (SELECT theta FROM ({thetas(g, b, candidates)}) ORDER BY cost_row_conditional, theta NULLS LAST LIMIT 1),"
                f" t AS (SELECT coalesce(theta, 9223372036854775807) AS theta FROM th), bb AS (SELECT {b} AS b), {placements(None)},"
                " hh AS MATERIALIZED (SELECT count(*) FILTER (coalesce(k, 0) < theta) AS ns, count(*) FILTER (coalesce(k, 0) >= theta) AS nd FROM t, v LEFT JOIN d ON node = s),"
                f" po AS MATERIALIZED (SELECT count(*) FILTER (cb <> rb) AS off FROM (SELECT DISTINCT {block('md5', 'src', b)} AS cb, {block('md5', 'dst', b)} AS rb, dst FROM e JOIN d ON src = s, t WHERE k < theta)),"
                " x AS (SELECT 'horizontal' AS method, b * n + n AS total FROM c, bb UNION ALL SELECT 'vertical', 2 * n + 2 * off FROM c, pv"
                " UNION ALL SELECT 'hybrid', ns + b * nd + n + 2 * off FROM c, bb, hh, po),"
                " y AS (SELECT * FROM x UNION ALL SELECT 'selected', total FROM x, c, bb WHERE method = CASE WHEN power(1 - m::DOUBLE / (n::DOUBLE * n), n::DOUBLE / b) < 0.5 THEN 'horizontal' ELSE 'vertical' END)"
                f" SELECT '{g}' AS graph, round(m / (n::DOUBLE * n), 12) AS density, {b}::INT AS b, method, total::BIGINT AS elements FROM y, c)"
            )
    return " UNION ALL ".join(rows)


def rmat(scale: int, draws: str, seed: int, quadrants: tuple[float, ...]) -> str:
    """Edges of the generator; draws: a scalar query."""
    a, b, c = (round(sum(quadrants[: k + 1]) * 65536) for k in range(3))
    parts = ", ".join(f"md5(id || '-{seed}-{p}') AS x{p}" for p in range(-(-scale // 8)))
    bits = ", ".join(f"('0x' || substr(x{k // 8}, {k % 8 * 4 + 1}, 4))::INT AS u{k}" for k in range(scale))
    src = " + ".join(f"(u{k} >= {b})::BIGINT * {1 << (scale - 1 - k)}" for k in range(scale))
    dst = " + ".join(f"((u{k} >= {a} AND u{k} < {b}) OR u{k} >= {c})::BIGINT * {1 << (scale - 1 - k)}" for k in range(scale))
    drawn = f"SELECT {bits} FROM (SELECT {parts} FROM (SELECT unnest(range(({draws})::BIGINT)) AS id))"
    return _pairs(f"SELECT {src} AS src, {dst} AS dst FROM ({drawn})")
