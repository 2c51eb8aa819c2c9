"""SQL twins of the operators, as common table expressions that DuckDB runs on the same tables."""

from __future__ import annotations

from trilist.functions.coins import sql_coefficient, sql_coin, sql_poly_hash
from trilist.sources.graphs import GRAPHS, vertices_sql

TRI = "tri AS (SELECT x.u AS a, x.v AS b, y.v AS c FROM e x JOIN e y ON x.v = y.u JOIN e z ON z.u = x.u AND z.v = y.v)"
SUP = """sup AS (SELECT e.u, e.v, count(t.u)::BIGINT AS support FROM e LEFT JOIN (SELECT a AS u, b AS v FROM tri UNION ALL SELECT a, c FROM tri UNION ALL SELECT b, c FROM tri) t
 ON e.u = t.u AND e.v = t.v GROUP BY e.u, e.v)"""
PSUP = "psup AS (SELECT x.dst AS u, y.dst AS v, count(*)::BIGINT AS support FROM a x JOIN a y ON x.src = y.src AND x.dst < y.dst GROUP BY 1, 2)"
DEG = "deg AS (SELECT src AS v, count(*)::BIGINT AS degree FROM a GROUP BY 1)"


def classes(threshold: str) -> str:
    return f"""cls AS (SELECT a, b, c, greatest(s1.support, s2.support, s3.support) AS max_support, greatest(s1.support, s2.support, s3.support) >= {threshold} AS is_heavy
 FROM tri JOIN sup s1 ON s1.u = a AND s1.v = b JOIN sup s2 ON s2.u = a AND s2.v = c JOIN sup s3 ON s3.u = b AND s3.v = c)"""


def params(eps: float) -> str:
    """One row: n, threshold, coin limits and caps, by the same rules as Params."""
    return f"""par AS (SELECT *, greatest(1, floor(pow(n, {eps} / 2) + 1e-9))::BIGINT AS buckets FROM (SELECT n, pow(n, {eps}) AS threshold, floor(least(1.0, pow(n, -{eps})) * 4294967296)::BIGINT AS s_limit,
 floor(4 * pow(n, 1 - {eps}) + 1e-9)::BIGINT AS s_cap, floor(least(1.0, 1 / (9 * pow(n, {eps}))) * 4294967296)::BIGINT AS x_limit, sqrt(54 * pow(n, 1 + {eps}) * ln(n)) AS r FROM (SELECT count(*)::DOUBLE AS n FROM vert)))"""


def graph(name: str, *more: str, eps: float | None = None) -> str:
    parts = [f"e AS MATERIALIZED ({GRAPHS[name].sql})", "a AS (SELECT u AS src, v AS dst FROM e UNION ALL SELECT v, u FROM e)", f"vert AS ({vertices_sql(name)})"]
    return "WITH RECURSIVE " + ", ".join([*parts, *([params(eps)] if eps is not None else []), *more]) + " "


def sort3(x: str, y: str, z: str) -> str:
    return f"least({x}, {y}, {z}) AS a, {x} + {y} + {z} - least({x}, {y}, {z}) - greatest({x}, {y}, {z}) AS b, greatest({x}, {y}, {z}) AS c"


def sample_ctes(seed: int, rep: int = 0, cap: str = "(SELECT s_cap FROM par)") -> list[str]:
    c = sql_coin(seed, rep, "'s'", "src", "dst")
    return [
        f"kept AS (SELECT src AS j, dst AS l FROM a WHERE {c} < (SELECT s_limit FROM par))",
        f"ssz AS (SELECT j, count(*) AS size, count(*) <= {cap} AS speaks FROM kept GROUP BY 1)",
        f"hs AS (SELECT DISTINCT x.dst AS node, {sort3('k.j', 'x.dst', 'k.l')} FROM kept k JOIN ssz USING (j) JOIN a x ON x.src = k.j AND x.dst <> k.l JOIN a z ON z.src = x.dst AND z.dst = k.l WHERE speaks)",
    ]


def hash_ctes(seed: int, rep: int = 0, buckets: str = "(SELECT buckets FROM par)", cap: str = "(SELECT floor(8 + 4 * n / buckets + 1e-9) FROM par)", suffix: str = "") -> list[str]:
    co = ", ".join(f"{sql_coefficient(seed, rep, 'v', k)} AS c{k}" for k in range(3))
    h = sql_poly_hash("y.dst", "c0", "c1", "c2", buckets)
    s = suffix
    return [
        f"hsh{s} AS (SELECT v AS node, {co} FROM (SELECT DISTINCT src AS v FROM a))",
        f"msg{s} AS (SELECT x.dst AS j, x.src AS a, y.dst AS l FROM hsh{s} JOIN a x ON x.src = node JOIN a y ON y.src = x.dst WHERE {h} = 0)",
        f"msz{s} AS (SELECT j, a, count(*) AS size, count(*) <= {cap} AS speaks FROM msg{s} GROUP BY 1, 2)",
        f"got{s} AS (SELECT DISTINCT a AS node, least(j, l) AS u, greatest(j, l) AS v FROM msg{s} JOIN msz{s} USING (j, a) WHERE speaks)",
        f"hh{s} AS (SELECT x.node, x.u AS a, x.v AS b, y.v AS c FROM got{s} x JOIN got{s} y ON x.node = y.node AND x.u = y.u AND x.v < y.v JOIN got{s} z ON z.node = x.node AND z.u = x.v AND z.v = y.v)",
    ]


def x_ctes(seed: int, rep: int = 0) -> list[str]:
    return [
        f"xs AS (SELECT v FROM vert WHERE {sql_coin(seed, rep, repr('x'), 'v')} < (SELECT x_limit FROM par))",
        "nx AS (SELECT src AS v, list_sort(list(dst)) AS xs FROM a WHERE dst IN (SELECT v FROM xs) GROUP BY 1)",
        "blocked AS (SELECT DISTINCT x.dst AS u, y.dst AS v FROM a x JOIN a y ON x.src = y.src AND x.dst < y.dst WHERE x.src IN (SELECT v FROM xs))",
    ]


def core_ctes(r: str, steps: int) -> list[str]:
    """The loop, unrolled; a stalled step repeats itself, so its output is the same and its trace ends there."""
    out = ["u1 AS (SELECT v FROM vert)"]
    for i in range(1, steps + 1):
        out += [
            f"au{i} AS (SELECT src, dst FROM a WHERE src IN (SELECT v FROM u{i}) AND dst IN (SELECT v FROM u{i}))",
            f"off{i} AS (SELECT x.dst AS j, x.src AS k, y.dst AS l FROM au{i} x JOIN au{i} y ON x.src = y.src AND x.dst <> y.dst ANTI JOIN blocked b ON b.u = least(x.dst, y.dst) AND b.v = greatest(x.dst, y.dst))",
            f"sz{i} AS (SELECT j, k, count(*) AS size FROM off{i} GROUP BY 1, 2)",
            f"ov{i} AS (SELECT j, k FROM sz{i} WHERE size > {r})",
            f"calm{i} AS (SELECT v FROM u{i} LEFT JOIN (SELECT j, count(*) AS n FROM ov{i} GROUP BY 1) ON j = v WHERE coalesce(n, 0) <= {r})",
            f"oa{i} AS (SELECT DISTINCT o.j AS node, {sort3('o.j', 'o.k', 'o.l')} FROM off{i} o JOIN sz{i} USING (j, k) JOIN a z ON z.src = o.j AND z.dst = o.l WHERE size <= {r})",
            f"ob{i} AS (SELECT DISTINCT y.dst AS node, {sort3('o.j', 'y.dst', 'o.k')} FROM ov{i} o JOIN calm{i} c ON c.v = o.j JOIN au{i} y ON y.src = o.j AND y.dst <> o.k JOIN au{i} z ON z.src = o.k AND z.dst = y.dst)",
            f"u{i + 1} AS (SELECT v FROM u{i} WHERE v NOT IN (SELECT v FROM calm{i}))",
        ]
    out.append("core AS (" + " UNION ".join(f"SELECT * FROM oa{i} UNION SELECT * FROM ob{i}" for i in range(1, steps + 1)) + ")")
    rows = " UNION ALL ".join(f"SELECT {i} AS i, (SELECT count(*) FROM u{i}) AS active, (SELECT count(*) FROM calm{i}) AS settled, (SELECT count(*) FROM ov{i}) AS overflow_pairs" for i in range(1, steps + 1))
    out.append(f"trace AS (SELECT i::BIGINT AS iteration, active::BIGINT AS active, settled::BIGINT AS settled, overflow_pairs::BIGINT AS overflow_pairs FROM (SELECT *, coalesce(min(settled) OVER (ORDER BY i ROWS BETWEEN UNBOUNDED PRECEDING AND 1 PRECEDING), 1) AS least FROM ({rows})) WHERE active > 0 AND least > 0)")
    return out
