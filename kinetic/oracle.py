"""The queries' answers in DuckDB's SQL, from the definitions rather than from the engine's plans."""

from __future__ import annotations

import re

from kinetic.sources import standins as st

Q = 10


def duck(expression: str) -> str:
    """An expression of the stand-ins in DuckDB's dialect."""
    e = re.sub(r"(?<![\w.])(-?\d+(?:\.\d+)?)D\b", r"CAST(\1 AS DOUBLE)", expression)
    e = e.replace(" div ", " // ").replace("unix_micros(ts)", "epoch_us(ts)").replace("get_json_object(", "json_extract_string(")
    e = re.sub(r"datediff\((\w+), date'([-\d]+)'\)", r"date_diff('day', DATE '\2', CAST(\1 AS DATE))", e)
    return re.sub(r"embedding\[(\d)\]", lambda m: f"embedding[{int(m[1]) + 1}]", e)


def _steps(source: str, steps: list[dict[str, str]], columns: str) -> str:
    for step in steps:
        source = f"(SELECT *, {', '.join(f'{duck(e)} AS {n}' for n, e in step.items())} FROM {source})"
    return f"SELECT {columns} FROM {source}"


_MO = "oid, x, y, vx, vy, speed, t_ref"


def orders(regime: str = "mix-L", any_direction: bool = False) -> str:
    return _steps("(SELECT * FROM orders JOIN customer ON o_custkey = c_custkey)", st.orders_expressions(regime, any_direction), _MO)


def lineitem(m: int | None = None) -> str:
    oid = "l_orderkey * 1000003 + l_linenumber * 7919 + l_partkey * 104729 + l_suppkey * 1299709 + CAST(round(l_extendedprice * 100) AS BIGINT) * 15485863 + CAST(l_quantity AS BIGINT) * 32452843 + CAST(date_diff('day', DATE '1992-01-01', CAST(l_shipdate AS DATE)) AS BIGINT) * 49979687"
    where = "" if m is None else f" WHERE (l_partkey * 7 + l_suppkey) % 6 < {m}"
    return _steps(f"(SELECT *, {oid} AS oid FROM lineitem{where})", st.lineitem_expressions(), _MO)


def events(rush: bool = False, oid: str = "user_id") -> str:
    return _steps(f"(SELECT *, {oid} AS oid FROM events)", st.events_expressions(rush), f"{_MO}, epoch_us(ts) AS us, hr, event_id, ts")


def embed() -> str:
    return _steps("(SELECT vec_id, embedding FROM embeddings)", st.embed_expressions(), _MO)


def ranges(window: int = 400, t: int = 60) -> str:
    return _steps("supplier", st.range_expressions(window, t), "qid, xlo, ylo, xhi, yhi, t")


def knns(k: int = 30, t: int = 60) -> str:
    return _steps("nation", st.knn_expressions(k, t), "qid, cx, cy, k, t")


def micro(e: str) -> str:
    return f"CAST(floor(({e}) * 1000000 + 0.5) AS BIGINT)"


def code(x: str, y: str, depth: int, side: float = 10000.0) -> str:
    g = {c: f"least({(1 << depth) - 1}, greatest(0, CAST(floor({c} / {side} * {1 << depth}) AS BIGINT)))" for c in (x, y)}
    return " | ".join(f"((({g[x]} >> {i}) & 1) << {2 * i}) | ((({g[y]} >> {i}) & 1) << {2 * i + 1})" for i in range(depth))


def layer_ctes(mo: str, q: int = Q, how: str = "equal_width") -> str:
    """mo, lm (mo with edge and top), layers."""
    head = f"mo AS ({mo})"
    if how == "equal_width":
        lm = f"wd AS (SELECT max(speed) / {q} AS w FROM mo), lm AS (SELECT mo.*, least({q}, greatest(1, CAST(ceil(speed / w) AS BIGINT))) AS edge, least({q}, greatest(1, CAST(ceil(speed / w) AS BIGINT))) * w AS top FROM mo, wd)"
    else:
        lm = "lm AS (SELECT mo.*, dense_rank() OVER (ORDER BY speed) AS edge, speed AS top FROM mo)"
    layers = "layers AS (SELECT row_number() OVER (ORDER BY edge) AS layer, edge, coalesce(lag(top) OVER (ORDER BY edge), 0) AS lo, top AS hi, CAST(sm AS BIGINT) / 1000000 / n AS rep, n FROM (SELECT edge, top, count(*) AS n, sum(CAST(floor(speed * 1000000 + 0.5) AS BIGINT)) AS sm FROM lm GROUP BY edge, top))"
    return f"{head}, {lm}, {layers}"


def cell_ctes(depth: int = 5) -> str:
    return f"fine AS (SELECT layer, {code('x', 'y', depth)} AS c FROM lm JOIN layers USING (edge)), cells AS (SELECT layer, CAST(lv AS BIGINT) AS level, c >> CAST(2 * ({depth} - lv) AS BIGINT) AS code, count(*) AS n FROM fine, generate_series(0, {depth}) AS g(lv) GROUP BY ALL)"


def test_ctes(bins: int = 2, critical: float = 7.814728, depth: int = 5) -> str:
    d = 1 if bins == 2 else 2
    b = bins * bins
    return f"tested AS (SELECT layer, level - {d} AS level, code >> {2 * d} AS code, sum(n) AS n, CAST(sum(n * n) * {b} AS DOUBLE) / CAST(sum(n) AS DOUBLE) - CAST(sum(n) AS DOUBLE) AS stat FROM cells WHERE level >= {d} AND level - {d} < {depth} GROUP BY layer, level - {d}, code >> {2 * d}), rough AS (SELECT layer, level, code FROM tested WHERE stat > {critical})"


def split_ctes(depth: int = 5) -> str:
    out = ["s0 AS (SELECT * FROM rough WHERE level = 0)"]
    for i in range(1, depth):
        out.append(f"s{i} AS (SELECT r.* FROM rough r JOIN s{i - 1} p ON p.layer = r.layer AND p.code = r.code >> 2 WHERE r.level = {i})")
    return ", ".join(out) + ", splits AS (" + " UNION ALL ".join(f"SELECT * FROM s{i}" for i in range(depth)) + ")"


#: Cells of any tree; a cell is in the tiling of (s, r] if none of those layers splits it and one splits its parent, or it is the root.
TILING = (
    "every AS (SELECT 0 AS level, 0 AS code UNION SELECT level + 1, code * 4 + k FROM splits, generate_series(0, 3) AS g(k)), "
    "span AS (SELECT a.s, b.r FROM (SELECT layer - 1 AS s FROM layers) a, (SELECT layer AS r FROM layers) b WHERE a.s < b.r), "
    "tiling AS (SELECT s, r, level, code FROM span, every e WHERE NOT EXISTS (SELECT 1 FROM splits x WHERE x.level = e.level AND x.code = e.code AND x.layer > s AND x.layer <= r) "
    "AND (e.level = 0 OR EXISTS (SELECT 1 FROM splits x WHERE x.level = e.level - 1 AND x.code = e.code >> 2 AND x.layer > s AND x.layer <= r)))"
)


def cost_ctes(c: int = 102, t: float = 120.0, grain: str = "part", rounding: str = "ceil") -> str:
    """cost(s, r, n, regions, v_one, v_quad, v, quadrants) from the definition: every layer of every region of every range."""
    choose = "lgamma(h + 1) - lgamma(h - ce + 1) - lgamma(total + 1) + lgamma(total - ce + 1)"
    nodes = {"ceil": f"ceil(total / {c}.0::double)", "floor": f"floor(total / {c}.0::double)"}[rounding]
    v = {"off": "one", "on": "quad", "part": "least(one, quad)", "region": "region", "speed": "by_speed"}[grain]
    return (
        "held AS (SELECT t.s, t.r, t.level, t.code, c.layer, c.n FROM tiling t JOIN cells c ON c.level = t.level AND c.code = t.code AND c.layer > t.s AND c.layer <= t.r), "
        f"cum AS (SELECT *, sum(n) OVER w AS h1, sum(n) OVER w - n AS h0, sum(n) OVER (PARTITION BY s, r, level, code) AS total FROM held WINDOW w AS (PARTITION BY s, r, level, code ORDER BY layer)), "
        f"pr AS (SELECT *, least({c}, total) AS ce FROM cum), "
        f"prob AS (SELECT *, CASE WHEN h1 < ce THEN 0 ELSE exp({choose.replace('(h ', '(h1 ')}) END - CASE WHEN h0 < ce THEN 0 ELSE exp({choose.replace('(h ', '(h0 ')}) END AS p FROM pr), "
        f"term AS (SELECT s, r, level, code, total, p, rep AS v, 10000.0::double / pow(2, level) * sqrt(ce / total::double) AS d, {nodes} AS k FROM prob JOIN layers USING (layer)), "
        f"reg AS (SELECT s, r, level, code, any_value(total) AS total, sum(p * k * (d * d * {t} + 2 * d * v * {t} * {t} + 4.0::double / 3 * v * v * {t} * {t} * {t})) AS one, sum(p * k * (4 * d * d * {t} + 2 * d * v * {t} * {t} + v * v * {t} * {t} * {t} / 3)) AS quad, "
        f"sum(p * k * least(d * d * {t} + 2 * d * v * {t} * {t} + 4.0::double / 3 * v * v * {t} * {t} * {t}, 4 * d * d * {t} + 2 * d * v * {t} * {t} + v * v * {t} * {t} * {t} / 3)) AS by_speed FROM term GROUP BY s, r, level, code), "
        "tot AS (SELECT s, r, sum(total) AS n, sum(one) AS one, sum(quad) AS quad, sum(least(one, quad)) AS region, sum(by_speed) AS by_speed FROM reg GROUP BY s, r), "
        f"cost AS (SELECT s, r, n, (SELECT count(*) FROM tiling g WHERE g.s = tot.s AND g.r = tot.r) AS regions, one AS v_one, quad AS v_quad, {v} AS v, {dict(off='0', on='1').get(grain, 'CAST(quad < one AS INT)')} AS quadrants FROM tot)"
    )


#: The cheapest of all plans, by listing them; ties to fewer parts and slower cuts do not occur in the data.
PLAN = (
    "nq AS (SELECT max(layer) AS q FROM layers), masks AS (SELECT m, q FROM nq, generate_series(0, (SELECT CAST(pow(2, max(layer) - 1) AS BIGINT) - 1 FROM layers)) AS g(m)), "
    "cuts AS (SELECT m, layer AS i FROM masks, layers WHERE layer = q OR (m >> (layer - 1)) & 1 = 1), "
    "pieces AS (SELECT m, coalesce(lag(i) OVER (PARTITION BY m ORDER BY i), 0) AS s, i AS r FROM cuts), "
    "priced AS (SELECT m, sum(v) AS total, count(*) AS k FROM pieces JOIN cost USING (s, r) GROUP BY m), "
)


def plan_ctes(k: int | None = None) -> str:
    where = "" if k is None else f"WHERE k = {k} "
    return PLAN + (
        f"best AS (SELECT m FROM priced {where}ORDER BY total, m LIMIT 1), "
        "plan AS (SELECT row_number() OVER (ORDER BY r) AS part, s AS lo_layer, r AS hi_layer, coalesce((SELECT hi FROM layers WHERE layer = s), 0) AS lo, (SELECT hi FROM layers WHERE layer = r) AS hi, quadrants, v AS cost FROM pieces JOIN best USING (m) JOIN cost USING (s, r))"
    )


def optimiser(mo: str, q: int = Q, grain: str = "part", rounding: str = "ceil", c: int = 102, k: int | None = None) -> str:
    return ", ".join([layer_ctes(mo, q), cell_ctes(), test_ctes(), split_ctes(), TILING, cost_ctes(c, grain=grain, rounding=rounding), plan_ctes(k)])


def optimiser_by_prefixes(mo: str, q: int, c: int = 102) -> str:
    """The same plan for more layers than masks can list: the least cost of every prefix, then the way back. Needs WITH RECURSIVE."""
    steps = (
        "nq AS (SELECT max(layer) AS q FROM layers), dp AS (SELECT CAST(0 AS BIGINT) AS r, [0.0::double] AS best, [CAST(0 AS BIGINT)] AS last "
        "UNION ALL SELECT dp.r + 1, list_append(best, (SELECT min(best[s + 1] + v) FROM cost WHERE cost.r = dp.r + 1)), list_append(last, (SELECT arg_min(s, best[s + 1] + v) FROM cost WHERE cost.r = dp.r + 1)) FROM dp, nq WHERE dp.r < q), "
        "done AS (SELECT last FROM dp, nq WHERE r = q), way AS (SELECT q AS r, last[q + 1] AS s FROM done, nq UNION ALL SELECT s, last[s + 1] FROM way, done WHERE s > 0), "
        "plan AS (SELECT row_number() OVER (ORDER BY r) AS part, s AS lo_layer, r AS hi_layer, coalesce((SELECT hi FROM layers WHERE layer = s), 0) AS lo, (SELECT hi FROM layers WHERE layer = r) AS hi, quadrants, v AS cost FROM way JOIN cost USING (s, r))"
    )
    return ", ".join([layer_ctes(mo, q), cell_ctes(), test_ctes(), split_ctes(), TILING, cost_ctes(c), steps])


_QUADRANT = "2 * CAST(vx >= 0 AS INT) + CAST(vy >= 0 AS INT)"
PARTED = f"parted AS (SELECT mo.*, p.part, CASE WHEN p.quadrants = 1 THEN {_QUADRANT} ELSE 0 END AS quadrant FROM mo JOIN plan p ON (p.part = 1 OR speed > p.lo) AND (p.part = (SELECT max(part) FROM plan) OR speed <= p.hi))"


def node_ctes(c: int = 102) -> str:
    return (
        "col AS (SELECT *, least(4095, greatest(0, CAST(floor((x + vx * (0 - t_ref)) / 10000.0::double * 4096) AS BIGINT))) AS gc FROM parted), "
        "cc AS (SELECT part, quadrant, gc, count(*) AS n FROM col GROUP BY ALL), "
        f"strips AS (SELECT part, quadrant, gc, CAST((sum(n) OVER (PARTITION BY part, quadrant ORDER BY gc) - n) * CAST(ceil(sqrt(sum(n) OVER (PARTITION BY part, quadrant) / {c}.0::double)) AS BIGINT) // sum(n) OVER (PARTITION BY part, quadrant) AS BIGINT) AS strip FROM cc), "
        f"objects AS (SELECT col.* EXCLUDE (gc), strip * 1048576 + (row_number() OVER (PARTITION BY part, quadrant, strip ORDER BY y, oid) - 1) // {c} AS node FROM col JOIN strips USING (part, quadrant, gc)), "
        "nodes AS (SELECT part, quadrant, node, count(*) AS n, min(x) AS xlo, max(x) AS xhi, min(y) AS ylo, max(y) AS yhi, min(vx) AS vxlo, max(vx) AS vxhi, min(vy) AS vylo, max(vy) AS vyhi FROM objects GROUP BY ALL)"
    )


HITS = (
    "hits AS (SELECT q.qid, n.part, n.quadrant, n.node FROM nodes n JOIN q ON n.xlo + least(n.vxlo * t, n.vxhi * t) <= q.xhi AND n.xhi + greatest(n.vxlo * t, n.vxhi * t) >= q.xlo "
    "AND n.ylo + least(n.vylo * t, n.vyhi * t) <= q.yhi AND n.yhi + greatest(n.vylo * t, n.vyhi * t) >= q.ylo)"
)


def range_answers(mo: str, q: str) -> str:
    return f"WITH mo AS ({mo}), q AS ({q}) SELECT qid, oid, x + vx * (t - t_ref) AS px, y + vy * (t - t_ref) AS py FROM mo JOIN q ON x + vx * (t - t_ref) BETWEEN xlo AND xhi AND y + vy * (t - t_ref) BETWEEN ylo AND yhi"


def knn_answers(mo: str, q: str) -> str:
    return (
        f"WITH mo AS ({mo}), q AS ({q}), d AS (SELECT qid, oid, k, (x + vx * (t - t_ref) - cx) * (x + vx * (t - t_ref) - cx) + (y + vy * (t - t_ref) - cy) * (y + vy * (t - t_ref) - cy) AS dist2 FROM mo, q) "
        "SELECT qid, row_number() OVER (PARTITION BY qid ORDER BY dist2, oid) AS rank, oid, dist2 FROM d QUALIFY row_number() OVER (PARTITION BY qid ORDER BY dist2, oid) <= max(k) OVER (PARTITION BY qid)"
    )


def range_counts(mo: str, q: str) -> str:
    return f"SELECT qid, count(*) AS answers FROM ({range_answers(mo, q)}) GROUP BY qid"
