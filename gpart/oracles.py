"""DuckDB SQL for the registered queries, as chains of common table expressions that share no code with the Spark plans."""

from __future__ import annotations

M = 2_147_483_647

#: The first expressions of each graph: pairs (a, b, w), each undirected edge once, and more keys k if vertices may be isolated.
PAIRS: dict[str, str] = {
    "copurchase": "d AS (SELECT DISTINCT l_orderkey AS o, l_partkey AS p FROM lineitem), pairs AS (SELECT x.p AS a, y.p AS b, count(*) AS w FROM d x JOIN d y ON x.o = y.o AND x.p < y.p GROUP BY 1, 2)",
    "cust_supp": "pairs AS (SELECT o_custkey AS a, l_suppkey + 1000000000 AS b, count(*) AS w FROM lineitem JOIN orders ON l_orderkey = o_orderkey GROUP BY 1, 2)",
    "fk_tree": "pairs AS (SELECT o_custkey + 1000 AS a, o_orderkey + 1000000000 AS b, 1 AS w FROM orders UNION SELECT c_nationkey + 100, c_custkey + 1000, 1 FROM customer UNION SELECT n_regionkey, n_nationkey + 100, 1 FROM nation)",
    "event_chain": "l AS (SELECT event_id AS e, lag(event_id) OVER (PARTITION BY user_id ORDER BY ts, event_id) AS p FROM events), pairs AS (SELECT least(e, p) AS a, greatest(e, p) AS b, 1 AS w FROM l WHERE p IS NOT NULL), more AS (SELECT event_id AS k FROM events)",
    "event_window": "o AS (SELECT event_id AS e, row_number() OVER (ORDER BY ts, event_id) AS r FROM events), pairs AS (SELECT least(x.e, y.e) AS a, greatest(x.e, y.e) AS b, 1 AS w FROM o x JOIN o y ON y.r BETWEEN x.r + 1 AND x.r + 4), more AS (SELECT event_id AS k FROM events)",
    "page_host": "d AS (SELECT DISTINCT page_id AS p, regexp_extract(url, '//([^/]+)/', 1) AS h FROM pages), pairs AS (SELECT x.p AS a, y.p AS b, count(*) AS w FROM d x JOIN d y ON x.h = y.h AND x.p < y.p WHERE x.h <> '' GROUP BY 1, 2)",
    "page_path": "t AS (SELECT page_id, unnest(regexp_extract_all(html, 'href=\"([^\"]*)\"', 1)) AS t FROM pages), pairs AS (SELECT 'p' || page_id AS a, 't' || t AS b, count(*) AS w FROM t GROUP BY 1, 2)",
    "doc_line_links": "l AS (SELECT DISTINCT doc_id AS p, trim(t, ' ') AS h FROM (SELECT doc_id, unnest(string_split(text, chr(10))) AS t FROM documents) WHERE len(trim(t, ' ')) > 20), s AS (SELECT h FROM l GROUP BY 1 HAVING count(*) >= 2), pairs AS (SELECT 'd' || p AS a, 'l' || md5(h) AS b, 1 AS w FROM l JOIN s USING (h))",
    "token_bigram": "t AS (SELECT list_filter(regexp_split_to_array(lower(text), '[ \\n\\t\\r]+'), lambda x: x <> '') AS ws FROM documents), g AS (SELECT unnest(ws[1:len(ws) - 1]) AS x, unnest(ws[2:len(ws)]) AS y FROM t WHERE len(ws) > 1), pairs AS (SELECT least(x, y) AS a, greatest(x, y) AS b, count(*) AS w FROM g WHERE x <> y GROUP BY 1, 2)",
    "knn8": "v AS (SELECT vec_id AS i, list_transform(embedding, lambda x: CAST(x AS DOUBLE)) AS v FROM embeddings), n AS (SELECT x.i AS x, y.i AS y, row_number() OVER (PARTITION BY x.i ORDER BY round(list_dot_product(x.v, y.v) / (sqrt(list_dot_product(x.v, x.v)) * sqrt(list_dot_product(y.v, y.v))), 9) DESC, y.i) AS r FROM v x JOIN v y ON x.i <> y.i), pairs AS (SELECT DISTINCT least(x, y) AS a, greatest(x, y) AS b, 1 AS w FROM n WHERE r <= 8)",
    "bench_overlap": "it AS (SELECT 'i' || item_id AS k, list_filter(regexp_split_to_array(lower(text), '[ \\n\\t\\r]+'), lambda x: x <> '') AS ws FROM benchmark), dt AS (SELECT 'd' || doc_id AS k, list_filter(regexp_split_to_array(lower(text), '[ \\n\\t\\r]+'), lambda x: x <> '') AS ws FROM documents), ig AS (SELECT DISTINCT k, array_to_string(ws[i:i + 7], ' ') AS g FROM (SELECT k, ws, unnest(range(1, len(ws) - 6)) AS i FROM it WHERE len(ws) >= 8)), dg AS (SELECT DISTINCT k, array_to_string(ws[i:i + 7], ' ') AS g FROM (SELECT k, ws, unnest(range(1, len(ws) - 6)) AS i FROM dt WHERE len(ws) >= 8)), pairs AS (SELECT DISTINCT dg.k AS a, ig.k AS b, 1 AS w FROM ig JOIN dg USING (g)), more AS (SELECT 'i' || item_id AS k FROM benchmark)",
    "conv_turns": "t AS (SELECT 't' || conv_id || '_' || turn AS k, 'r' || role AS r, conv_id, turn FROM conversations), f AS (SELECT k, lead(k) OVER (PARTITION BY conv_id ORDER BY turn) AS n FROM t), pairs AS (SELECT least(k, n) AS a, greatest(k, n) AS b, 1 AS w FROM f WHERE n IS NOT NULL UNION SELECT r, k, 1 FROM t)",
    "doc_label": "pairs AS (SELECT DISTINCT -1 - 2 * quality - toxic AS a, doc_id AS b, 1 AS w FROM labels)",
}


def graph(name: str) -> str:
    """Expressions down to ids (k, id), vertices (id, w) and edges (src, dst, w)."""
    more = " UNION SELECT k FROM more" if "more AS" in PAIRS[name] else ""
    return PAIRS[name] + (
        f", keys AS (SELECT a AS k FROM pairs UNION SELECT b FROM pairs{more}), ids AS (SELECT k, row_number() OVER (ORDER BY k) - 1 AS id FROM keys)"
        ", half AS (SELECT x.id AS s, y.id AS t, CAST(w AS BIGINT) AS w FROM pairs JOIN ids x ON x.k = a JOIN ids y ON y.k = b)"
        ", vertices AS (SELECT id, CAST(1 AS BIGINT) AS w FROM ids), edges AS MATERIALIZED (SELECT s AS src, t AS dst, w FROM half UNION ALL SELECT t, s, w FROM half)"
    )


def full(name: str, select: str, *more: str) -> str:
    return "WITH " + ", ".join([graph(name), *more]) + " " + select


def h(x: str, seed: int = 0) -> str:
    return f"(({x}) * 48271 + {seed}) % {M}"


def vlen(x: str) -> str:
    return "(1" + "".join(f" + CAST(({x}) >= {1 << 7 * n} AS INT)" for n in range(1, 9)) + ")"


def zz(x: str) -> str:
    return f"(CASE WHEN ({x}) >= 0 THEN 2 * ({x}) ELSE -2 * ({x}) - 1 END)"


def lp_step(old: str, new: str, seed: int, part: int, parts: int, cap: int | None = None) -> str:
    """One synchronous sub-batch from labels `old` to labels `new`."""
    room = f"AND (r.c = o.c OR cw.w + v.w <= {cap})" if cap is not None else ""
    out = f"""{new}_r AS (SELECT e.src AS id, l.c, CAST(sum(e.w) AS BIGINT) AS rating FROM edges e JOIN {old} l ON l.id = e.dst WHERE {h("e.src", seed)} % {parts} = {part} GROUP BY 1, 2),
{new}_w AS (SELECT l.c, CAST(sum(v.w) AS BIGINT) AS w FROM {old} l JOIN vertices v USING (id) GROUP BY 1),
{new}_b AS (SELECT r.id, r.c, o.c AS own, r.rating, v.w, row_number() OVER (PARTITION BY r.id ORDER BY r.rating DESC, CAST(r.c = o.c AS INT) DESC, {h("r.c", seed)}, r.c) AS place
  FROM {new}_r r JOIN {old} o ON o.id = r.id JOIN vertices v ON v.id = r.id JOIN {new}_w cw ON cw.c = r.c WHERE true {room}),
{new}_m AS (SELECT id, c, rating, w FROM {new}_b WHERE place = 1 AND c <> own)"""
    if cap is not None:
        out += f""",
{new}_q AS (SELECT m.*, sum(m.w) OVER (PARTITION BY m.c ORDER BY m.rating DESC, {h("m.id", seed)}, m.id ROWS UNBOUNDED PRECEDING) AS run, coalesce(cw.w, 0) AS now FROM {new}_m m LEFT JOIN {new}_w cw ON cw.c = m.c),
{new}_a AS (SELECT id, c FROM {new}_q WHERE run + now <= {cap})"""
    source = f"{new}_a" if cap is not None else f"{new}_m"
    return out + f""",
{new} AS MATERIALIZED (SELECT o.id, coalesce(m.c, o.c) AS c FROM {old} o LEFT JOIN {source} m USING (id))"""


def lp(rounds: int, parts: int = 2, seed: int = 1, cap: int | None = None) -> list[str]:
    """Expressions l0 (singletons) to the last, and its name."""
    out, name, n = ["l0 AS (SELECT id, id AS c FROM vertices)"], "l0", 0
    for r in range(rounds):
        for part in range(parts):
            n += 1
            out.append(lp_step(name, f"l{n}", seed + r, part, parts, cap))
            name = f"l{n}"
    return [*out, f"labels AS (SELECT id, c FROM {name})"]


CONTRACT = """cv AS (SELECT c, CAST(sum(v.w) AS BIGINT) AS w, row_number() OVER (ORDER BY c) - 1 AS id FROM labels JOIN vertices v USING (id) GROUP BY c),
ce AS (SELECT x.id AS src, y.id AS dst, CAST(sum(e.w) AS BIGINT) AS w FROM edges e JOIN labels a ON a.id = e.src JOIN labels b ON b.id = e.dst JOIN cv x ON x.c = a.c JOIN cv y ON y.c = b.c WHERE a.c <> b.c GROUP BY 1, 2)"""


def blocks(k: int, seed: int = 1) -> str:
    return f"part AS (SELECT id, CAST({h('id', seed)} % {k} AS INT) AS block FROM vertices)"


AFFINITY = "aff AS (SELECT e.src AS id, p.block, CAST(sum(e.w) AS BIGINT) AS affinity FROM edges e JOIN part p ON p.id = e.dst GROUP BY 1, 2)"
DEGREES = "deg AS (SELECT v.id, count(e.dst) AS degree, CAST(coalesce(sum(e.w), 0) AS BIGINT) AS u FROM vertices v LEFT JOIN edges e ON e.src = v.id GROUP BY 1), off AS (SELECT id, degree, u, CAST(coalesce(sum(degree) OVER (ORDER BY id ROWS BETWEEN UNBOUNDED PRECEDING AND 1 PRECEDING), 0) AS BIGINT) AS first_edge FROM deg)"


def coded(intervals: bool = True, weighted: bool = False) -> list[str]:
    """Expressions down to sizes (id, n_bytes): the bytes of each vertex's row by the codec's layout."""
    long = "len >= 3" if intervals else "false"
    out = [
        DEGREES,
        "e1 AS (SELECT src, dst, w, dst - row_number() OVER (PARTITION BY src ORDER BY dst) AS run FROM edges)",
        f"e2 AS (SELECT *, {long} AS big FROM (SELECT *, count(*) OVER (PARTITION BY src, run) AS len FROM e1))",
        "iv AS (SELECT src, min(dst) AS s, count(*) AS len FROM e2 WHERE big GROUP BY src, run)",
        "iv2 AS (SELECT src, s, len, s - lag(s + len - 1) OVER (PARTITION BY src ORDER BY s) - 2 AS g FROM iv)",
        f"ib AS (SELECT src AS id, count(*) AS n, sum({vlen('coalesce(g, ' + zz('s - src') + ')')} + {vlen('len - 3')}) AS b FROM iv2 GROUP BY 1)",
        "lo AS (SELECT src, dst, dst - lag(dst) OVER (PARTITION BY src ORDER BY dst) - 1 AS g FROM e2 WHERE NOT big)",
        f"lb AS (SELECT src AS id, sum({vlen('coalesce(g, ' + zz('dst - src') + ')')}) AS b FROM lo GROUP BY 1)",
    ]
    weights, join = "0", ""
    if weighted:
        out.append("wd AS (SELECT src, w - lag(w, 1, 0) OVER (PARTITION BY src ORDER BY CAST(big AS INT) DESC, dst) AS x FROM e2)")
        out.append(f"wb AS (SELECT src AS id, sum({vlen(zz('x'))}) AS b FROM wd GROUP BY 1)")
        weights, join = "coalesce(wb.b, 0)", "LEFT JOIN wb USING (id)"
    flag = "CAST(ib.n IS NOT NULL AS INT)"
    head = vlen(f"2 * first_edge + {flag}")
    out.append(f"sizes AS (SELECT off.id, degree, first_edge, CAST({head} + CASE WHEN ib.n IS NULL THEN 0 ELSE {vlen('ib.n')} END + coalesce(ib.b, 0) + coalesce(lb.b, 0) + {weights} AS BIGINT) AS n_bytes FROM off LEFT JOIN ib USING (id) LEFT JOIN lb USING (id) {join})")
    return out


def checks(*rows: tuple[str, int]) -> str:
    """The expected table of a query that reports violations."""
    return "SELECT * FROM (VALUES " + ", ".join(f"('{name}', CAST({value} AS BIGINT))" for name, value in rows) + ") t(check_name, value)"
