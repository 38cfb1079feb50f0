"""Building blocks of the reference SQL: named common table expressions, joined as far as a query needs them."""

from __future__ import annotations

import re

from ..encoder.layers import bias, weights
from ..functions.hashing import uniform_sql

D, TAGS = 8, 4


def num(x: float) -> str:
    """A literal that SQL reads as a double."""
    return f"{x!r}e0" if "e" not in repr(x) else repr(x)


def vsum(x: str, d: int = D) -> str:
    return "[" + ", ".join(f"sum(({x})[{i + 1}])" for i in range(d)) + "]"


def vmean(x: str, d: int = D) -> str:
    return "[" + ", ".join(f"avg(({x})[{i + 1}])" for i in range(d)) + "]"


def vmap(x: str, f: str, d: int = D) -> str:
    """f is an expression with {} where a component stands."""
    return "[" + ", ".join(f.format(f"({x})[{i + 1}]") for i in range(d)) + "]"


def vzip(a: str, b: str, f: str, d: int = D) -> str:
    return "[" + ", ".join(f.format(f"({a})[{i + 1}]", f"({b})[{i + 1}]") for i in range(d)) + "]"


def vdot(a: str, b: str, d: int = D) -> str:
    return "(" + " + ".join(f"({a})[{i + 1}] * ({b})[{i + 1}]" for i in range(d)) + ")"


def vcosine(a: str, b: str, d: int = D) -> str:
    n = f"(sqrt({vdot(a, a, d)}) * sqrt({vdot(b, b, d)}))"
    return f"CASE WHEN {n} > 0 THEN {vdot(a, b, d)} / {n} ELSE 0.0e0 END"


def columns(x: str, d: int = D, name: str = "x") -> str:
    return ", ".join(f"round(({x})[{i + 1}], 6) + 0.0e0 AS {name}{i}" for i in range(d))


def vzeros(d: int = D) -> str:
    return "[" + ", ".join(["0.0e0"] * d) + "]"


def sigmoid(x: str) -> str:
    return f"(1.0e0 / (1.0e0 + exp(-({x}))))"


def matvec(matrix, x: str, b) -> list[str]:
    return ["(" + " + ".join(f"{num(w)} * ({x})[{j + 1}]" for j, w in enumerate(row)) + f" + {num(c)})" for row, c in zip(matrix, b)]


def dense(matrix, x: str, b) -> str:
    return "[" + ", ".join(sigmoid(r) for r in matvec(matrix, x, b)) + "]"


def layer(source: str, agg: str, seed: int) -> str:
    return f"SELECT e.g, {dense(weights(D, 2 * D, seed), 'list_concat(e.vec, a.agg)', bias(D, seed))} AS vec FROM {source} e JOIN {agg} a USING (g)"


def neighbours(vectors: str) -> str:
    return f"""SELECT e.g, coalesce(x.agg, {vzeros()}) AS agg FROM {vectors} e LEFT JOIN (
      SELECT l.dst AS g, {vsum(vmap('s.vec', '{} * l.lap'))} AS agg FROM lap_home l JOIN {vectors} s ON s.g = l.src GROUP BY l.dst) x USING (g)"""


DAY = "date_diff('day', DATE '1970-01-01', {}::DATE)::BIGINT"


def split_of(lines: str) -> str:
    return f"""SELECT l.*, CASE WHEN day <= cut THEN 'train' ELSE 'test' END AS split,
      CASE WHEN day <= cut THEN least(3, floor((day - t0) / ((cut - t0) / 4)))::INTEGER END AS slice
      FROM {lines} l, (SELECT quantile_cont(day, 0.8) AS cut, min(day) AS t0 FROM {lines})"""


CTES: dict[str, str] = {
    "lines": f"""SELECT o.o_custkey AS u, c.c_nationkey::BIGINT AS nk, l.l_partkey AS v, l.l_suppkey AS s, {DAY.format('o.o_orderdate')} AS day, l.l_extendedprice AS price
      FROM lineitem l JOIN orders o ON l.l_orderkey = o.o_orderkey JOIN customer c ON c.c_custkey = o.o_custkey""",
    "segments": "SELECT c_mktsegment, dense_rank() OVER (ORDER BY c_mktsegment) - 1 AS k FROM (SELECT DISTINCT c_mktsegment FROM customer)",
    "home": "SELECT c_custkey AS u, (c_nationkey * 5 + k)::BIGINT AS g FROM customer JOIN segments USING (c_mktsegment)",
    "mem_home": "SELECT h.g, h.u, min(day) AS first_day, max(day) AS last_day, count(day) AS n FROM home h LEFT JOIN lines USING (u) GROUP BY 1, 2",
    "mem_market": "SELECT s * 25 + nk AS g, u, min(day) AS first_day, max(day) AS last_day, count(*) AS n FROM lines GROUP BY 1, 2",
    "kinds": "SELECT p_brand, p_type, (dense_rank() OVER (ORDER BY p_brand, p_type) - 1)::BIGINT AS g FROM (SELECT DISTINCT p_brand, p_type FROM part)",
    "mem_taste": "SELECT k.g, l.u, min(day) AS first_day, max(day) AS last_day, count(*) AS n FROM lines l JOIN part p ON p.p_partkey = l.v JOIN kinds k ON k.p_brand = p.p_brand AND k.p_type = p.p_type GROUP BY 1, 2 HAVING count(*) >= 2",
    "gl_home": "SELECT g, v, day, price FROM lines JOIN home USING (u)",
    "gl_market": "SELECT s * 25 + nk AS g, v, day, price FROM lines",
    "sliced_home": split_of("gl_home"),
    "sliced_market": split_of("gl_market"),
    "counts_home": "SELECT g, slice, count(*) AS n FROM sliced_home WHERE slice IS NOT NULL GROUP BY 1, 2",
    "common_market": "SELECT x.g AS a, y.g AS b, count(*) AS common FROM mem_market x JOIN mem_market y ON x.u = y.u AND x.g < y.g GROUP BY 1, 2",
    "bought": "SELECT DISTINCT v, u, day FROM lines",
    "friends": "SELECT a, b, count(*) AS items FROM (SELECT DISTINCT x.u AS a, y.u AS b, x.v FROM bought x JOIN bought y ON x.v = y.v AND x.u < y.u AND abs(x.day - y.day) <= 30) GROUP BY 1, 2",
    "lift_home": "SELECT least(x.g, y.g) AS a, greatest(x.g, y.g) AS b, count(*) AS friends FROM friends f JOIN home x ON x.u = f.a JOIN home y ON y.u = f.b WHERE x.g <> y.g GROUP BY 1, 2",
    "edges_home": """SELECT least(src, dst) AS a, greatest(src, dst) AS b, max(w) AS w FROM (
      SELECT *, row_number() OVER (PARTITION BY src ORDER BY w DESC, dst) AS n FROM (
        SELECT a AS src, b AS dst, friends AS w FROM lift_home UNION ALL SELECT b, a, friends FROM lift_home)) WHERE n <= 10 GROUP BY 1, 2""",
    "sym_home": "SELECT a AS src, b AS dst FROM edges_home UNION ALL SELECT b, a FROM edges_home",
    "deg_home": "SELECT src AS g, count(*) AS deg FROM sym_home GROUP BY 1",
    "lap_home": "SELECT src, dst, x.deg AS deg_src, y.deg AS deg_dst, 1 / sqrt((x.deg * y.deg)::DOUBLE) AS lap FROM sym_home JOIN deg_home x ON x.g = src JOIN deg_home y ON y.g = dst",
    "iv": f"SELECT p.p_partkey AS v, list_transform(e.embedding[1:{D}], lambda x: x::DOUBLE) AS vec FROM part p JOIN embeddings e ON e.vec_id = p.p_partkey % (SELECT count(*) FROM embeddings)",
    "uv": f"SELECT u, {vmean('vec')} AS vec FROM lines JOIN iv USING (v) GROUP BY 1",
    "pg_home": f"SELECT g, {vmean('vec')} AS vec FROM mem_home JOIN uv USING (u) GROUP BY 1",
    "pg_market": f"SELECT g, {vmean('vec')} AS vec FROM mem_market JOIN uv USING (u) GROUP BY 1",
    "tags": "SELECT v, unnest(list_sort(list_distinct(list_filter(list_concat(string_split(p_name, ' '), [p_brand, p_type]), lambda t: t <> '')))) AS tag FROM (SELECT p_partkey AS v, p_name, p_brand, p_type FROM part)",
    "tagvec": "SELECT v, " + vmean("x", TAGS) + " AS vec FROM (SELECT v, [" + ", ".join(f"2 * {uniform_sql(f'tag{i}', 'tag')} - 1" for i in range(TAGS)) + "] AS x FROM tags) GROUP BY 1",
    "pairs_home": "SELECT DISTINCT g, v FROM gl_home",
    "gtag_home": f"SELECT g, {vmean('vec', TAGS)} AS vec FROM pairs_home JOIN tagvec USING (v) GROUP BY 1",
    "e0_home": f"SELECT p.g, {dense(weights(D, D + TAGS, 0), f'list_concat(p.vec, coalesce(t.vec, {vzeros(TAGS)}))', bias(D, 0))} AS vec FROM pg_home p LEFT JOIN gtag_home t USING (g)",
    "e0_item": f"SELECT p.v, {dense(weights(D, D + TAGS, 1), f'list_concat(p.vec, coalesce(t.vec, {vzeros(TAGS)}))', bias(D, 1))} AS vec FROM iv p LEFT JOIN tagvec t USING (v)",
    "agg0_home": neighbours("e0_home"),
    "e1_home": layer("e0_home", "agg0_home", 2),
    "agg1_home": neighbours("e1_home"),
    "e2_home": layer("e1_home", "agg1_home", 3),
    "und_home": "SELECT src AS a, dst AS b, lap, deg_src AS deg_a, deg_dst AS deg_b, least((src // 5) % 5, (dst // 5) % 5) AS ci, greatest((src // 5) % 5, (dst // 5) % 5) AS cj FROM lap_home WHERE src < dst",
    "window_items": "SELECT * FROM e0_item WHERE v % 50 = 0",
    "activity": f"SELECT h.g, {DAY.format('e.ts')} AS day FROM events e JOIN home h ON h.u = e.user_id",
    "act_home": "SELECT g, count(CASE WHEN day > now - 7 THEN 1 END) AS recent, count(*) AS total, count(CASE WHEN day > now - 7 THEN 1 END) / count(*)::DOUBLE AS act FROM activity, (SELECT max(day) - 10 AS now FROM activity) WHERE day <= now GROUP BY g",
    "sim_home": f"SELECT src, dst, {vcosine('x.vec', 'y.vec')} AS sim FROM sym_home JOIN e2_home x ON x.g = src JOIN e2_home y ON y.g = dst",
    "will_home": f"SELECT v, g, {sigmoid(vdot('i.vec', 'e.vec'))} AS will FROM window_items i, e2_home e",
    "graph_home": """SELECT a.v, s.src, s.dst, coalesce(t.act, 0.0e0) AS a_src, a.will AS w_src, b.will AS w_dst, s.sim,
      0.1e0 * (coalesce(t.act, 0.0e0) * a.will) + 0.7e0 * s.sim + (1 - 0.1e0 - 0.7e0) * b.will AS p
      FROM sim_home s LEFT JOIN act_home t ON t.g = s.src JOIN will_home a ON a.g = s.src JOIN will_home b ON b.g = s.dst AND b.v = a.v""",
}


def compose(main: str, extra: dict[str, str] | None = None) -> str:
    """The query with all expressions that it names, directly or through others, in an order that SQL accepts."""
    known, order, state = CTES | (extra or {}), [], {}

    def visit(text: str) -> None:
        for word in dict.fromkeys(re.findall(r"\w+", text)):
            if word in known and word not in state:
                state[word] = 1
                visit(known[word])
                order.append(word)

    visit(main)
    head = ",\n".join(f"{n} AS MATERIALIZED ({known[n]})" for n in order)
    recursive = "RECURSIVE " if any("UNION" in known[n] and re.search(rf"\bFROM {n}\b|\bJOIN {n}\b", known[n]) for n in order) else ""
    return f"WITH {recursive}{head}\n{main}" if order else main
