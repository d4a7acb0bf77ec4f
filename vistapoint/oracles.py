"""DuckDB SQL for the registered queries. It states its own constants and shares no arithmetic with the library's plans."""

from __future__ import annotations

import math

from .functions.noise import u01_sql
from .operators.fov import GAMMA20, VARIANTS
from .plans.query import Area, ClusterOptions, Query
from .sources.carriers import CENTRE, JITTER_M, NOISE_HALF, SPOTS

# Metres per degree of latitude, radius of the earth, peaks of the normal densities by sigma.
METRES, EARTH_M = 111320.0, 6371008.8
PEAKS = {15.0: 0.02659615202676218, 25.0: 0.015957691216057307}
# Cells per side of the square regions by their side and the cell's, in degrees.
SIDES = {(0.003, 0.0001): 30, (0.008, 0.0001): 80, (0.008, 0.0005): 16, (0.008, 0.001): 8, (0.05, 0.0001): 500, (0.12, 0.0001): 1200, (0.35, 0.0001): 3500}
#: Metres per degree of longitude at each row's latitude.
OWN = f"({METRES!r}::DOUBLE * cos(radians(lat)))"


def mx(lat: float) -> str:
    """Metres per degree of longitude at a latitude."""
    return f"{METRES * math.cos(math.radians(lat))!r}::DOUBLE"


def side(query: Query) -> int:
    a = query.area
    assert round(a.max_lat - a.min_lat, 6) == round(a.max_lon - a.min_lon, 6)
    return SIDES[round(a.max_lat - a.min_lat, 6), round(query.cell, 6)]


MX, MY = mx(10.0), f"{METRES!r}::DOUBLE"


def _list(values) -> str:
    return "[" + ", ".join(f"{v!r}::DOUBLE" for v in values) + "]"


def pmod360(x: str) -> str:
    return f"((({x}) % 360.0::DOUBLE) + 360.0::DOUBLE) % 360.0::DOUBLE"


def angle_diff(a: str, b: str) -> str:
    return f"abs({pmod360(f'({a}) - ({b}) + 180.0::DOUBLE')} - 180.0::DOUBLE)"


def alpha(variant: str, noise: str) -> str:
    share = VARIANTS[variant]
    return "60.0::DOUBLE" if share is None else f"CASE WHEN {noise} < {share} THEN 160.0::DOUBLE ELSE 360.0::DOUBLE END"


def _placed(rows: str, variant: str, extra: str = "", centre: tuple[float, float] = CENTRE) -> str:
    key = "fov_id"
    brg = f"(360.0::DOUBLE * {u01_sql('brg', key)})"
    return f"""SELECT fov_id, video_id,
      CASE WHEN noisy THEN {centre[0] - NOISE_HALF!r}::DOUBLE + {2 * NOISE_HALF!r}::DOUBLE * {u01_sql("y", key)} ELSE spot_lat + away_m * cos(radians({brg})) / {MY} END AS lat,
      CASE WHEN noisy THEN {centre[1] - NOISE_HALF!r}::DOUBLE + {2 * NOISE_HALF!r}::DOUBLE * {u01_sql("x", key)} ELSE spot_lon + away_m * sin(radians({brg})) / {mx(centre[0])} END AS lon,
      CASE WHEN noisy THEN {brg} ELSE {pmod360(f"{brg} + 180.0::DOUBLE + aim")} END AS theta,
      1000.0::DOUBLE * 0.35::DOUBLE * {_list(GAMMA20)}[floor({u01_sql("rad", "video_id")} * 20)::INT + 1] AS r_m,
      {alpha(variant, u01_sql("ang", key))} AS alpha, t{extra} FROM ({rows})"""


def fov_events(variant: str = "pie60", centre: tuple[float, float] = CENTRE) -> str:
    spot = f"floor(12.0::DOUBLE * pow({u01_sql('hot', 'user_id')}, 1.5::DOUBLE))::INT + 1"
    rows = f"""SELECT event_id AS fov_id, user_id AS video_id, ts AS t,
      {centre[0]!r}::DOUBLE + {_list(s[0] for s in SPOTS)}[{spot}] + ({u01_sql("jy", "user_id")} - 0.5::DOUBLE) * {JITTER_M!r}::DOUBLE / {MY} AS spot_lat,
      {centre[1]!r}::DOUBLE + {_list(s[1] for s in SPOTS)}[{spot}] + ({u01_sql("jx", "user_id")} - 0.5::DOUBLE) * {JITTER_M!r}::DOUBLE / {mx(centre[0])} AS spot_lon,
      value AS away_m, ((props::JSON->>'$.k')::INT - 49.5::DOUBLE) * 0.6::DOUBLE AS aim, event_type = 'error' AS noisy FROM events"""
    return _placed(rows, variant, centre=centre)


_LATTICE = f"{CENTRE[0]!r}::DOUBLE + (floor(nation / 5) - 2) * 0.06::DOUBLE AS spot_lat, {CENTRE[1]!r}::DOUBLE + (nation % 5 - 2) * 0.06::DOUBLE AS spot_lon"


def fov_orders(variant: str = "pie60") -> str:
    rows = f"""SELECT *, {_LATTICE} FROM (SELECT o_orderkey AS fov_id, o_custkey AS video_id, o_orderdate::TIMESTAMP AS t, c_nationkey::BIGINT AS nation,
      1.0::DOUBLE + 0.0002::DOUBLE * o_totalprice::DOUBLE AS away_m, ({u01_sql("aim", "o_orderkey")} - 0.5::DOUBLE) * 60.0::DOUBLE AS aim, o_orderpriority = '5-LOW' AS noisy,
      n_name AS nation_name, r_name AS region_name
      FROM orders JOIN customer ON o_custkey = c_custkey JOIN nation ON c_nationkey = n_nationkey JOIN region ON n_regionkey = r_regionkey)"""
    return _placed(rows, variant, ", nation_name, region_name")


def fov_lineitem(variant: str = "pie60") -> str:
    key = "md5(l_orderkey || ':' || l_partkey || ':' || l_suppkey || ':' || l_linenumber)"
    rows = f"""SELECT *, {_LATTICE} FROM (SELECT ('0x' || substr({key}, 1, 13))::BIGINT AS fov_id, o_custkey AS video_id, l_shipdate::TIMESTAMP AS t, c_nationkey::BIGINT AS nation,
      3.0::DOUBLE * l_quantity::DOUBLE AS away_m, (l_discount::DOUBLE - 0.05::DOUBLE) * 600.0::DOUBLE AS aim, o_orderpriority = '5-LOW' AS noisy
      FROM lineitem JOIN orders ON l_orderkey = o_orderkey JOIN customer ON o_custkey = c_custkey)"""
    return _placed(rows, variant)


def mbr(fov: str, mode: str = "exact") -> str:
    """fov with its upright bounding box."""
    if mode == "circle":
        west, east, south, north = "-r_m", "r_m", "-r_m", "r_m"
    else:
        lo, hi = "radians(theta - alpha / 2)", "radians(theta + alpha / 2)"
        holds = lambda a: f"(alpha >= 360 OR {angle_diff('theta', f'{a}::DOUBLE')} <= alpha / 2)"
        xs, ys = f"0.0::DOUBLE, r_m * sin({lo}), r_m * sin({hi})", f"0.0::DOUBLE, r_m * cos({lo}), r_m * cos({hi})"
        west, east = f"CASE WHEN {holds(270)} THEN -r_m ELSE least({xs}) END", f"CASE WHEN {holds(90)} THEN r_m ELSE greatest({xs}) END"
        south, north = f"CASE WHEN {holds(180)} THEN -r_m ELSE least({ys}) END", f"CASE WHEN {holds(0)} THEN r_m ELSE greatest({ys}) END"
    return f"SELECT *, lat + ({south}) / {MY} AS min_lat, lat + ({north}) / {MY} AS max_lat, lon + ({west}) / {OWN} AS min_lon, lon + ({east}) / {OWN} AS max_lon FROM ({fov})"


def box(a: Area) -> str:
    return f"max_lat >= {a.min_lat!r}::DOUBLE AND min_lat <= {a.max_lat!r}::DOUBLE AND max_lon >= {a.min_lon!r}::DOUBLE AND min_lon <= {a.max_lon!r}::DOUBLE"


def in_range(fov: str, a: Area, where: str = "true") -> str:
    return f"SELECT * FROM ({fov}) WHERE {box(a)} AND {where}"


def ci_columns(query: Query) -> str:
    """The fixed-point intention from dx, dy, theta, r_m, alpha."""
    m = query.model
    d = "sqrt(dx * dx + dy * dy)"
    off = f"CASE WHEN dx = 0 AND dy = 0 THEN 0.0::DOUBLE ELSE {angle_diff(pmod360('degrees(atan2(dx, dy))'), 'theta')} END"
    if m.kind == "full_coverage":
        return f"CASE WHEN {d} <= r_m AND (alpha >= 360 OR ({off}) <= alpha / 2) THEN 1000000000000::BIGINT ELSE 0 END"
    if m.kind == "center_line":
        return f"CASE WHEN {d} <= r_m AND dx * sin(radians(theta)) + dy * cos(radians(theta)) >= 0 AND abs(dx * cos(radians(theta)) - dy * sin(radians(theta))) <= {m.line_width_m / 2!r}::DOUBLE THEN 1000000000000::BIGINT ELSE 0 END"
    normal = lambda x, s: f"exp(-(({x}) * ({x})) / {2 * s * s!r}::DOUBLE) * {PEAKS[s]!r}::DOUBLE"
    angular = f"CASE WHEN ({off}) <= alpha / 2 THEN {normal(off, m.sigma_angle)} ELSE 0.0::DOUBLE END"
    if m.circular == "constant":
        angular = f"CASE WHEN alpha >= 360 THEN 1.0::DOUBLE ELSE {angular} END"
    radius = "r_m" if m.reach is None else f"least(r_m, {m.reach * m.sigma_distance!r}::DOUBLE)"
    return f"round((({angular}) * (CASE WHEN {d} <= {radius} THEN {normal(d, m.sigma_distance)} ELSE 0.0::DOUBLE END)) * 1000000000000.0::DOUBLE)::BIGINT"


def span(fov: str, query: Query) -> str:
    """The cells of each bounding box, carried from the plane at its own latitude into the plane at the area's."""
    a, c, n = query.area, query.cell, side(query)
    low = lambda v, o: f"greatest(floor(({v} - {o!r}::DOUBLE) / {c!r}::DOUBLE - 1e-6), 0)::BIGINT"
    high = lambda v, o: f"least(floor(({v} - {o!r}::DOUBLE) / {c!r}::DOUBLE + 1e-6), {n - 1})::BIGINT"
    flat = lambda v: f"(lon + ({v} - lon) * (cos(radians(lat)) / {math.cos(math.radians(query.lat0))!r}::DOUBLE))"
    return f"SELECT * FROM (SELECT *, {low(flat('min_lon'), a.min_lon)} AS x0, {high(flat('max_lon'), a.min_lon)} AS x1, {low('min_lat', a.min_lat)} AS y0, {high('max_lat', a.min_lat)} AS y1 FROM ({fov})) WHERE x0 <= x1 AND y0 <= y1"


def relative(cells: str, query: Query) -> str:
    """dx, dy: metres from the camera to the centre of (cell_x, cell_y)."""
    a, c = query.area, query.cell
    return f"SELECT *, ({a.min_lon!r}::DOUBLE + (cell_x + 0.5::DOUBLE) * {c!r}::DOUBLE - lon) * {mx(query.lat0)} AS dx, ({a.min_lat!r}::DOUBLE + (cell_y + 0.5::DOUBLE) * {c!r}::DOUBLE - lat) * {MY} AS dy FROM {cells}"


def pairs(fov: str, query: Query, keys: str = "", limits: str = "") -> str:
    """keys, cell_x, cell_y, ci_fixed of all positive pairs, by the cells of each bounding box. fov must be in range."""
    prefix = f"{keys}, " if keys else ""
    spans = f"SELECT * REPLACE ({limits}) FROM ({span(fov, query)})" if limits else span(fov, query)
    cells = f"(SELECT *, unnest(range(y0, y1 + 1)) AS cell_y FROM (SELECT *, unnest(range(x0, x1 + 1)) AS cell_x FROM ({spans}) WHERE x0 <= x1 AND y0 <= y1))"
    return f"SELECT {prefix}cell_x, cell_y, ci_fixed FROM (SELECT *, {ci_columns(query)} AS ci_fixed FROM ({relative(cells, query)})) WHERE ci_fixed > 0"


def naive(fov: str, query: Query, some: str = "true") -> str:
    """The matrix by all pairs of field of view and cell, without any box. some: which cells."""
    n = side(query)
    cells = f"(SELECT * FROM (SELECT i % {n} AS cell_x, i // {n} AS cell_y FROM range({n * n}) r(i) WHERE {some}), (SELECT lat, lon, theta, r_m, alpha FROM ({fov})))"
    return f"SELECT cell_x, cell_y, sum(ci_fixed)::BIGINT AS ci_fixed FROM (SELECT *, {ci_columns(query)} AS ci_fixed FROM ({relative(cells, query)})) WHERE ci_fixed > 0 GROUP BY cell_x, cell_y"


def naive_by_blocks(fov: str, query: Query, wide: int = 50) -> str:
    """The same over all cells of a large grid. All fields of view meet all blocks of wide x wide cells; where a block's nearest
    centre is beyond the visible distance, so are all of its cells, whose intentions are zero. All other cells are visited."""
    a, c, n = query.area, query.cell, side(query)
    m = -(-n // wide)
    gap = lambda v, o, b: f"greatest({o!r}::DOUBLE + ({b} + 0.5::DOUBLE) * {c!r}::DOUBLE - {v}, {v} - ({o!r}::DOUBLE + ({b} + {wide - 0.5}::DOUBLE) * {c!r}::DOUBLE), 0.0::DOUBLE)"
    near = f"sqrt(pow({gap('lon', a.min_lon, 'bx')} * {mx(query.lat0)}, 2) + pow({gap('lat', a.min_lat, 'by_')} * {MY}, 2)) <= r_m + 0.001::DOUBLE"
    blocks = f"(SELECT * FROM (SELECT i % {m} * {wide} AS bx, i // {m} * {wide} AS by_ FROM range({m * m}) r(i)), (SELECT lat, lon, theta, r_m, alpha FROM ({fov})) WHERE {near})"
    cells = f"(SELECT *, unnest(range(by_, least(by_ + {wide}, {n}))) AS cell_y FROM (SELECT *, unnest(range(bx, least(bx + {wide}, {n}))) AS cell_x FROM {blocks}))"
    return f"SELECT cell_x, cell_y, sum(ci_fixed)::BIGINT AS ci_fixed FROM (SELECT *, {ci_columns(query)} AS ci_fixed FROM ({relative(cells, query)})) WHERE ci_fixed > 0 GROUP BY cell_x, cell_y"


def matrix(fov: str, query: Query) -> str:
    return f"SELECT cell_x, cell_y, sum(ci_fixed)::BIGINT AS ci_fixed FROM ({pairs(fov, query)}) GROUP BY cell_x, cell_y"


def top(matrix_sql: str, k: int) -> str:
    return f"SELECT row_number() OVER (ORDER BY ci_fixed DESC, cell_y, cell_x) AS rank, cell_x, cell_y, round(ci_fixed / 1000000000000.0::DOUBLE, 6) AS ci FROM ({matrix_sql}) ORDER BY ci_fixed DESC, cell_y, cell_x LIMIT {k}"


def fov_with_mbr(variant: str, centre: tuple[float, float] = CENTRE) -> str:
    return mbr(fov_events(variant, centre))


def top_of(query: Query, variant: str, where: str = "true", centre: tuple[float, float] = CENTRE) -> str:
    return top(matrix(in_range(fov_with_mbr(variant, centre), query.area, where), query), query.k)


def _cell(query: Query) -> tuple[float, float]:
    return query.cell * METRES * math.cos(math.radians(query.lat0)), query.cell * METRES


def greedy_by(pairs_sql: str, by: str, k: int, query: Query) -> str:
    """by, diff_m, within, pairs: the greedy pairing of many pairs of lists at once. pairs_sql: by, i, j, ax, ay, bx, by_."""
    w, h = _cell(query)
    first = f"QUALIFY row_number() OVER (PARTITION BY {by} ORDER BY d, i, j) = 1"
    out = f"WITH p AS MATERIALIZED (SELECT {by}, i, j, sqrt(pow((ax - bx) * {w!r}::DOUBLE, 2.0) + pow((ay - by_) * {h!r}::DOUBLE, 2.0)) AS d FROM ({pairs_sql}))"
    same = " AND ".join(f"g.{c.strip()} = p.{c.strip()}" for c in by.split(","))
    for s in range(k):
        used = "".join(f" AND NOT EXISTS (SELECT 1 FROM g{t} g WHERE {same} AND (g.i = p.i OR g.j = p.j))" for t in range(s))
        out += f", g{s} AS MATERIALIZED (SELECT * FROM p WHERE true{used} {first})"
    every = " UNION ALL ".join(f"SELECT * FROM g{s}" for s in range(k))
    return f"{out} SELECT {by}, round(sum(d), 6) AS diff_m, sum(d) AS total, count(*) FILTER (d <= 20) AS within, count(*) AS pairs FROM ({every}) GROUP BY {by}"


def greedy(left: str, right: str, query: Query, within: float = 20.0) -> str:
    """diff_m, within, pairs of two top-k lists; the k steps are unrolled."""
    w, h = _cell(query)
    out = f"WITH l AS MATERIALIZED ({left}), r AS MATERIALIZED ({right}), p AS MATERIALIZED (SELECT l.rank AS i, r.rank AS j, sqrt(pow((l.cell_x - r.cell_x) * {w!r}::DOUBLE, 2.0) + pow((l.cell_y - r.cell_y) * {h!r}::DOUBLE, 2.0)) AS d FROM l, r)"
    for s in range(query.k):
        used = "".join(f" AND i NOT IN (SELECT i FROM g{t}) AND j NOT IN (SELECT j FROM g{t})" for t in range(s))
        out += f", g{s} AS MATERIALIZED (SELECT * FROM p WHERE true{used} ORDER BY d, i, j LIMIT 1)"
    every = " UNION ALL ".join(f"SELECT * FROM g{s}" for s in range(query.k))
    return f"{out} SELECT round(coalesce(sum(d), 0), 6) AS diff_m, count(*) FILTER (d <= {within}) AS within, count(*) AS pairs FROM ({every})"


def haversine(lat1: str, lon1: str, lat2: str, lon2: str) -> str:
    return f"{2 * EARTH_M!r}::DOUBLE * asin(sqrt(pow(sin(radians({lat2} - {lat1}) / 2), 2) + cos(radians({lat1})) * cos(radians({lat2})) * pow(sin(radians({lon2} - {lon1}) / 2), 2)))"


def clustered(variant: str, query: Query, o: ClusterOptions, result: str, shifts: bool = False, extra: str = "") -> str:
    """Clustered incremental sampling in running sums. result selects from its common table expressions; shifts adds the movement of lists, extra further expressions."""
    shifts = shifts or o.rule in ("topk_shift", "any_of", "all_of")
    a, c, n = query.area, query.cell, side(query)
    cte = [f"f AS MATERIALIZED (SELECT *, (lon - {a.min_lon!r}::DOUBLE) * {mx(query.lat0)} AS px, (lat - {a.min_lat!r}::DOUBLE) * {MY} AS py FROM ({in_range(fov_with_mbr(variant), a)}))"]
    cte.append(f"s AS MATERIALIZED (SELECT * FROM f WHERE {u01_sql('cluster' + o.salt, 'fov_id')} < {o.cluster_fraction})")
    cte.append(f"c0 AS MATERIALIZED (SELECT row_number() OVER (ORDER BY u, fov_id) - 1 AS i, px AS cx, py AS cy FROM (SELECT *, {u01_sql('init' + o.salt, 'fov_id')} AS u FROM s) ORDER BY u, fov_id LIMIT {o.clusters})")
    assign = lambda pts, ctr: f"SELECT fov_id, any_value(px) AS px, any_value(py) AS py, arg_min(i, ((px - cx) * (px - cx) + (py - cy) * (py - cy), i)) AS i FROM {pts}, {ctr} GROUP BY fov_id"
    for step in range(o.lloyd_steps):
        cte.append(f"c{step + 1} AS MATERIALIZED (SELECT c.i, coalesce(m.px, c.cx) AS cx, coalesce(m.py, c.cy) AS cy FROM c{step} c LEFT JOIN (SELECT i, avg(px) AS px, avg(py) AS py FROM ({assign('s', f'c{step}')}) GROUP BY i) m ON m.i = c.i)")
    last = f"c{o.lloyd_steps}"
    cte.append(f"radii AS MATERIALIZED (SELECT x.i AS cluster_id, any_value(cx) AS cx, any_value(cy) AS cy, count(*) AS n, sqrt(avg((px - cx) * (px - cx) + (py - cy) * (py - cy))) AS rms_m FROM ({assign('s', last)}) x JOIN {last} c ON c.i = x.i GROUP BY x.i)")
    cte.append(
        f"""rects AS MATERIALIZED (SELECT *, greatest({a.min_lon!r}::DOUBLE, {a.min_lon!r}::DOUBLE + (cx - rms_m) / {mx(query.lat0)}) AS r_min_lon, least({a.max_lon!r}::DOUBLE, {a.min_lon!r}::DOUBLE + (cx + rms_m) / {mx(query.lat0)}) AS r_max_lon,
        greatest({a.min_lat!r}::DOUBLE, {a.min_lat!r}::DOUBLE + (cy - rms_m) / {MY}) AS r_min_lat, least({a.max_lat!r}::DOUBLE, {a.min_lat!r}::DOUBLE + (cy + rms_m) / {MY}) AS r_max_lat FROM radii)"""
    )
    cell = lambda v, origin, n: f"least(greatest(floor(({v} - {origin!r}::DOUBLE) / {c!r}::DOUBLE), 0), {n - 1})::BIGINT"
    cte.append(f"ranges AS MATERIALIZED (SELECT *, {cell('r_min_lon', a.min_lon, n)} AS cx0, {cell('r_max_lon', a.min_lon, n)} AS cx1, {cell('r_min_lat', a.min_lat, n)} AS cy0, {cell('r_max_lat', a.min_lat, n)} AS cy1 FROM rects WHERE r_min_lon <= r_max_lon AND r_min_lat <= r_max_lat)")
    cte.append(f"mem AS MATERIALIZED (SELECT *, ntile({o.batches}) OVER (PARTITION BY cluster_id ORDER BY {u01_sql('batch' + o.salt, 'fov_id')}, fov_id) AS batch FROM (SELECT f.*, cluster_id, cx0, cx1, cy0, cy1 FROM f JOIN ranges ON f.max_lat >= r_min_lat AND f.min_lat <= r_max_lat AND f.max_lon >= r_min_lon AND f.min_lon <= r_max_lon))")
    limits = "greatest(x0, cx0) AS x0, least(x1, cx1) AS x1, greatest(y0, cy0) AS y0, least(y1, cy1) AS y1"
    cte.append(f"sums AS MATERIALIZED (SELECT cluster_id, cell_x, cell_y, batch, sum(ci_fixed)::BIGINT AS add FROM ({pairs('SELECT * FROM mem', query, 'cluster_id, batch', limits)}) GROUP BY ALL)")
    # A cell is in a list only if its last sum is at least the k-th largest of the first round: sums never fall.
    cte.append(f"least_sum AS MATERIALIZED (SELECT cluster_id, min(add) AS least, count(*) AS n FROM (SELECT * FROM sums WHERE batch = 1 QUALIFY row_number() OVER (PARTITION BY cluster_id ORDER BY add DESC) <= {query.k}) GROUP BY cluster_id)")
    cte.append(f"may AS MATERIALIZED (SELECT t.cluster_id, cell_x, cell_y FROM (SELECT cluster_id, cell_x, cell_y, sum(add) AS total FROM sums GROUP BY ALL) t LEFT JOIN least_sum l ON l.cluster_id = t.cluster_id WHERE l.n IS NULL OR l.n < {query.k} OR total >= least)")
    cte.append(f"dense AS MATERIALIZED (SELECT d.cluster_id, d.cell_x, d.cell_y, d.iter, sum(coalesce(s.add, 0)) OVER (PARTITION BY d.cluster_id, d.cell_x, d.cell_y ORDER BY d.iter)::BIGINT AS ci_fixed FROM (SELECT *, unnest(range(1, {o.rounds + 1})) AS iter FROM (SELECT cluster_id, cell_x, cell_y FROM may)) d LEFT JOIN sums s ON s.cluster_id = d.cluster_id AND s.cell_x = d.cell_x AND s.cell_y = d.cell_y AND s.batch = d.iter)")
    cte.append(f"ranked AS MATERIALIZED (SELECT * FROM (SELECT *, row_number() OVER (PARTITION BY cluster_id, iter ORDER BY ci_fixed DESC, cell_y, cell_x) AS rank FROM dense WHERE ci_fixed > 0) WHERE rank <= {query.k})")
    cte.append("shares AS MATERIALIZED (SELECT cluster_id, batch AS iter, sum(n) OVER (PARTITION BY cluster_id ORDER BY batch)::BIGINT AS seen, sum(n) OVER (PARTITION BY cluster_id ORDER BY batch) / sum(n) OVER (PARTITION BY cluster_id)::DOUBLE AS p FROM (SELECT cluster_id, batch, count(*) AS n FROM mem GROUP BY ALL))")
    cte.append("maxima AS MATERIALIZED (SELECT m.*, seen, p, lag(max_fixed) OVER w AS before, lag(p) OVER w AS p_before FROM (SELECT cluster_id, iter, max(ci_fixed) AS max_fixed FROM ranked GROUP BY ALL) m JOIN shares USING (cluster_id, iter) WINDOW w AS (PARTITION BY cluster_id ORDER BY iter))")
    change = {"raw": "abs(max_fixed - before) / 1e12::DOUBLE", "relative": "abs(max_fixed - before) / greatest(max_fixed, 1)::DOUBLE", "rescaled": "abs(max_fixed / p - before / p_before) / 1e12::DOUBLE", "rescaled_relative": "abs(max_fixed / p - before / p_before) / greatest(max_fixed / p, 1.0)"}[o.measure]
    cte.append(f"moves AS MATERIALIZED (SELECT *, {change} AS d_max FROM maxima)")
    by_max, by_shift = f"d_max < {o.threshold}", f"d_topk < {o.shift_threshold_m}"
    holds = {"max_change": by_max, "none": "false", "topk_shift": by_shift, "any_of": f"({by_max} OR {by_shift})", "all_of": f"({by_max} AND {by_shift})"}[o.rule]
    if shifts:
        before = "SELECT a.cluster_id, a.iter, a.rank AS i, b.rank AS j, a.cell_x AS ax, a.cell_y AS ay, b.cell_x AS bx, b.cell_y AS by_ FROM ranked a JOIN ranked b ON a.cluster_id = b.cluster_id AND a.iter = b.iter + 1"
        cte.append(f"shifts AS MATERIALIZED ({greedy_by(before, 'cluster_id, iter', query.k, query)})")
        cte.append("steps AS MATERIALIZED (SELECT moves.*, shifts.total AS d_topk FROM moves LEFT JOIN shifts USING (cluster_id, iter))")
    else:
        cte.append("steps AS MATERIALIZED (SELECT * FROM moves)")
    cte.append(f"stops AS MATERIALIZED (SELECT cluster_id, coalesce(min(iter) FILTER ({holds} AND iter >= {o.min_iterations}), max(iter)) AS stop FROM steps GROUP BY cluster_id)")
    cte.append("merged AS MATERIALIZED (SELECT cell_x, cell_y, max(round(ci_fixed / p)::BIGINT) AS ci_fixed FROM ranked JOIN stops ON ranked.cluster_id = stops.cluster_id AND ranked.iter = stops.stop JOIN shares ON shares.cluster_id = ranked.cluster_id AND shares.iter = ranked.iter GROUP BY ALL)")
    return "WITH " + ",\n".join([*cte, *([extra] if extra else [])]) + "\n" + result


