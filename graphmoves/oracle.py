"""DuckDB SQL for graphs, scores and whole moving phases, unrolled into a chain of common table expressions."""

from __future__ import annotations

U32 = "CAST('0x' || substr(md5({}), 1, 8) AS BIGINT)"

_SAME_ORDER = "SELECT a.{k} AS a, b.{k} AS b, count(*) AS w FROM lineitem a JOIN lineitem b ON a.l_orderkey = b.l_orderkey AND a.{k} < b.{k} GROUP BY 1, 2"


def planted_sql(mu: float = 0.4, seed: int = 7, degree: int = 20) -> str:
    inner, outer = round(degree / 2 * (1 - mu)), round(degree / 2 * mu)
    draw = lambda kind: U32.format(f"'{kind}:' || x || ':' || j || ':{seed}'")
    many = lambda n: f"(SELECT unnest(range(1, {n + 1})) AS j)"
    return f"""
        WITH numbered AS (SELECT c_custkey AS x, c_nationkey AS k, row_number() OVER (ORDER BY c_nationkey, c_custkey) - 1 AS pos FROM customer),
        spans AS (SELECT k, min(pos) AS lo, count(*) AS s FROM numbered GROUP BY k),
        drawn AS (SELECT x, lo + {draw('in')} % s AS pos FROM numbered JOIN spans USING (k), {many(inner)}),
        ends AS (
            SELECT drawn.x, numbered.x AS y FROM drawn JOIN numbered USING (pos)
            UNION ALL SELECT x, {draw('out')} % (SELECT count(*) FROM customer) AS y FROM numbered, {many(outer)})
        SELECT DISTINCT least(x, y) AS a, greatest(x, y) AS b, CAST(1 AS BIGINT) AS w FROM ends WHERE x <> y"""


_SHINGLES = """SELECT DISTINCT {i}, unnest(CASE WHEN len(ws) >= 5 THEN [array_to_string(ws[j : j + 4], ' ') FOR j IN range(1, len(ws) - 3)] ELSE [] END) AS g
    FROM (SELECT {i}, list_filter(regexp_split_to_array({t}, '\\s+'), lambda x: x <> '') AS ws FROM {f})"""

GRAPH_SQL = {
    "trade": "SELECT 2 * o_custkey AS a, 2 * l_suppkey + 1 AS b, count(*) AS w FROM lineitem JOIN orders ON l_orderkey = o_orderkey GROUP BY 1, 2",
    "basket": "SELECT 2 * o_custkey AS a, 2 * l_partkey + 1 AS b, count(*) AS w FROM lineitem JOIN orders ON l_orderkey = o_orderkey GROUP BY 1, 2",
    "copurchase": _SAME_ORDER.format(k="l_partkey"),
    "cosupply": _SAME_ORDER.format(k="l_suppkey"),
    "geo": """SELECT c_custkey * 4 AS a, CAST(c_nationkey AS BIGINT) * 4 + 2 AS b, CAST(1 AS BIGINT) AS w FROM customer
        UNION ALL SELECT s_suppkey * 4 + 1, CAST(s_nationkey AS BIGINT) * 4 + 2, 1 FROM supplier
        UNION ALL SELECT CAST(n_nationkey AS BIGINT) * 4 + 2, CAST(n_regionkey AS BIGINT) * 4 + 3, 1 FROM nation""",
    "planted": planted_sql(),
    "usage": "SELECT 2 * user_id AS a, 2 * CAST(props ->> '$.k' AS BIGINT) + 1 AS b, count(*) AS w FROM events WHERE props ->> '$.k' IS NOT NULL GROUP BY 1, 2",
    "coactive": """WITH e AS (SELECT DISTINCT user_id, date_trunc('hour', ts) AS h, event_type FROM events)
        SELECT x.user_id AS a, y.user_id AS b, count(*) AS w FROM e x JOIN e y ON x.h = y.h AND x.event_type = y.event_type AND x.user_id < y.user_id GROUP BY 1, 2""",
    "links": f"""SELECT DISTINCT 2 * page_id AS a, 2 * {U32.format('t')} + 1 AS b, CAST(1 AS BIGINT) AS w
        FROM (SELECT page_id, unnest(regexp_extract_all(html, 'href="([^"]*)"', 1)) AS t FROM pages)""",
    "neardup": f"""WITH s AS ({_SHINGLES.format(i='doc_id', t='text', f='documents')}), f AS (SELECT g FROM s GROUP BY g HAVING count(*) BETWEEN 2 AND 30)
        SELECT x.doc_id AS a, y.doc_id AS b, count(*) AS w FROM s x JOIN f USING (g) JOIN s y ON x.g = y.g AND x.doc_id < y.doc_id GROUP BY 1, 2 HAVING count(*) >= 5""",
    "knn": """WITH e AS (SELECT vec_id, CAST(embedding AS DOUBLE[]) AS v FROM embeddings),
        r AS (SELECT x.vec_id AS a, y.vec_id AS b, row_number() OVER (PARTITION BY x.vec_id ORDER BY round(list_cosine_similarity(x.v, y.v), 9) DESC, y.vec_id) AS r FROM e x JOIN e y ON x.vec_id <> y.vec_id)
        SELECT DISTINCT least(a, b) AS a, greatest(a, b) AS b, CAST(1 AS BIGINT) AS w FROM r WHERE r <= 5""",
    "bench_hits": f"""WITH s AS ({_SHINGLES.format(i='doc_id', t='lower(text)', f='documents')}), t AS ({_SHINGLES.format(i='item_id', t='lower(text)', f='benchmark')})
        SELECT 2 * doc_id AS a, 2 * item_id + 1 AS b, count(*) AS w FROM s JOIN t USING (g) GROUP BY 1, 2""",
    "talk": f"""SELECT DISTINCT 2 * conv_id AS a, 2 * {U32.format("lower(array_to_string(string_split(text, ' ')[1:2], ' '))")} + 1 AS b, CAST(1 AS BIGINT) AS w FROM conversations WHERE text IS NOT NULL""",
}
TRUTH = "SELECT c_custkey AS id, CAST(c_nationkey AS BIGINT) AS c FROM customer"


def graph_ctes(pairs: str, loops: str | None = None) -> str:
    return f"""pairs AS MATERIALIZED ({pairs}),
        edges AS MATERIALIZED (SELECT a AS src, b AS dst, CAST(w AS HUGEINT) AS w FROM pairs WHERE a <> b UNION ALL SELECT b, a, w FROM pairs WHERE a <> b),
        nodes AS MATERIALIZED (SELECT src AS id, sum(w) AS deg, CAST(0 AS HUGEINT) AS loop FROM edges GROUP BY 1),
        total AS MATERIALIZED (SELECT sum(deg) AS t FROM nodes)"""


def stats_sql(labels: str) -> str:
    return f"""SELECT v.c, v.vol, coalesce(i.w, 0) + v.loops AS inner_w, v.vol - coalesce(i.w, 0) - v.loops AS cut, v.size FROM
        (SELECT c, sum(deg) AS vol, sum(2 * loop) AS loops, count(*) AS size FROM {labels} JOIN nodes USING (id) GROUP BY c) v
        LEFT JOIN (SELECT x.c, sum(w) AS w FROM edges JOIN {labels} x ON x.id = src JOIN {labels} y ON y.id = dst WHERE x.c = y.c GROUP BY 1) i ON i.c = v.c"""


def p(z: str) -> str:
    return f"(CASE WHEN ({z}) > 0 THEN ({z}) * ln({z}) ELSE 0 END)"


def modularity_sql(stats: str) -> str:
    return f"SELECT round(sum(inner_w / t::DOUBLE - (vol / t::DOUBLE) * (vol / t::DOUBLE)), 9) AS q FROM {stats}, total"


def map_sql(stats: str) -> str:
    d = "t::DOUBLE"
    return f"""SELECT round((SELECT {p('sum(cut) / max(' + d + ')')} - 2 * sum({p('cut / ' + d)}) + sum({p('(cut + vol) / ' + d)}) FROM {stats}, total)
        - (SELECT sum({p('deg / ' + d)}) FROM nodes, total), 9) AS l"""


def rounds_ctes(objective: str, rounds: int, seed: int = 0, k: int = 4, start: str = "SELECT id, id AS c FROM nodes", name: str = "L") -> tuple[str, str]:
    """CTEs of whole rounds of synchronous local moving, and the name of the last labels."""
    out, last, step = [f"{name}0 AS MATERIALIZED ({start})"], f"{name}0", 0
    act = lambda v, rnd, i: U32.format(f"{v} || ':{rnd}:{seed}'") + f" % {k} = {i}"
    for rnd in range(rounds):
        for i in range(k):
            step += 1
            s = f"{name}{step}"
            out.append(f"{s}s AS MATERIALIZED ({stats_sql(last) if objective == 'map' else f'SELECT c, sum(deg) AS vol FROM {last} JOIN nodes USING (id) GROUP BY c'})")
            out.append(f"""{s}b AS MATERIALIZED (SELECT v, c, sum(x) AS x FROM (
                SELECT e.dst AS v, l.c, e.w AS x FROM edges e JOIN {last} l ON l.id = e.src WHERE {act('e.dst', rnd, i)}
                UNION ALL SELECT id, c, 0 FROM {last} WHERE {act('id', rnd, i)}) GROUP BY v, c)""")
            tie = U32.format(f"b.c || ':' || b.v || ':{seed}'")
            if objective == "modularity":
                score = "b.x * t - n.deg * (s.vol - CASE WHEN b.c = l.c THEN n.deg ELSE 0 END)"
                src = f"{s}b b JOIN {s}s s ON s.c = b.c JOIN nodes n ON n.id = b.v JOIN {last} l ON l.id = b.v, total"
            else:
                out.append(f"""{s}w AS MATERIALIZED (SELECT b.v, b.c, b.x, n.deg, n.loop, l.c AS a, s.cut AS raw,
                    s.vol - CASE WHEN b.c = l.c THEN n.deg ELSE 0 END AS vol, CASE WHEN b.c = l.c THEN s.cut - n.deg + 2 * n.loop + 2 * b.x ELSE s.cut END AS cut
                    FROM {s}b b JOIN {s}s s ON s.c = b.c JOIN nodes n ON n.id = b.v JOIN {last} l ON l.id = b.v)""")
                d = "t::DOUBLE"
                out.append(f"""{s}g AS MATERIALIZED (SELECT *, (SELECT sum(cut) FROM {s}s) - max(CASE WHEN c = a THEN raw END) OVER w + max(CASE WHEN c = a THEN cut END) OVER w AS s0, cut + deg - 2 * loop - 2 * x AS cu
                    FROM {s}w WINDOW w AS (PARTITION BY v))""")
                score = f"-round({p(f'(b.s0 - b.cut + b.cu) / {d}')} - 2 * ({p(f'b.cu / {d}')} - {p(f'b.cut / {d}')}) + ({p(f'(b.cu + b.vol + b.deg) / {d}')} - {p(f'(b.cut + b.vol) / {d}')}), 12)"
                src = f"{s}g b JOIN {last} l ON l.id = b.v, total"
            out.append(f"""{s}m AS MATERIALIZED (SELECT v, c FROM (SELECT b.v, b.c, row_number() OVER (PARTITION BY b.v ORDER BY {score} DESC, CASE WHEN b.c = l.c THEN 1 ELSE 0 END DESC, {tie} DESC, b.c DESC) AS r FROM {src}) WHERE r = 1)""")
            out.append(f"{s} AS MATERIALIZED (SELECT l.id, coalesce(m.c, l.c) AS c FROM {last} l LEFT JOIN {s}m m ON m.v = l.id)")
            last = s
    return ",\n".join(out), last


def moving_sql(pairs: str, objective: str, rounds: int, seed: int = 0) -> str:
    ctes, last = rounds_ctes(objective, rounds, seed)
    return f"WITH {graph_ctes(pairs)}, {ctes} SELECT id, c FROM {last}"


def ari_sql(one: str, two: str) -> str:
    c2 = "sum(n * (n - 1) / 2.0::DOUBLE)"
    return f"""cells AS MATERIALIZED (SELECT x.c AS x, y.c AS y, count(*) AS n FROM {one} x JOIN {two} y USING (id) GROUP BY 1, 2),
        sums AS (SELECT (SELECT {c2} FROM cells) AS s, (SELECT {c2} FROM (SELECT sum(n) AS n FROM cells GROUP BY x)) AS a,
            (SELECT {c2} FROM (SELECT sum(n) AS n FROM cells GROUP BY y)) AS b, (SELECT sum(n) * (sum(n) - 1) / 2.0::DOUBLE FROM cells) AS t)
        SELECT round((s - a * b / t) / ((a + b) / 2 - a * b / t), 9) AS ari FROM sums"""
