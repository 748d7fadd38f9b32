"""DuckDB SQL for the registered queries, written from the definitions and not from the plans."""

from __future__ import annotations

EVEN = """SELECT id, cx - hx AS xmin, cy - hy AS ymin, cx + hx AS xmax, cy + hy AS ymax FROM (
  SELECT o_orderkey AS id, CAST(date_diff('day', DATE '1995-01-01', CAST(o_orderdate AS DATE)) * 1000 AS DOUBLE) AS cx,
    CAST(floor(round(o_totalprice * 100) / 20) AS DOUBLE) AS cy, CAST(500 + 500 * (o_custkey % 7) AS DOUBLE) AS hx, CAST(500 + 300 * (o_orderkey % 11) AS DOUBLE) AS hy
  FROM orders)"""

_SKEW = """SELECT id, event_type, cx - hx AS xmin, cy - hy AS ymin, cx + hx AS xmax, cy + hy AS ymax FROM (
  SELECT id, event_type, cx, cy, CAST({hx} AS DOUBLE) AS hx, CAST({hy} AS DOUBLE) AS hy FROM (
    SELECT event_id AS id, event_type, round(value * 100) * 100 AS cx,
      round(coalesce(lead(value) OVER (PARTITION BY user_id ORDER BY ts, event_id), value) * 100) * 100 AS cy,
      (CAST(floor(1000000 / sqrt((SELECT count(*) FROM events))) AS BIGINT) * k * k * k * k * k * k) // 941480149401 AS h, (event_id // 2) % 2 AS o
    FROM (SELECT *, CAST(json_extract_string(props, '$.k') AS BIGINT) AS k FROM events)))"""
SKEW = _SKEW.format(hx="h * (1 + o)", hy="h * (2 - o)")
SKEW_WIDE = _SKEW.format(hx="h * 2", hy="h")
SPAN = """SELECT user_id * 100 + day(ts) AS id, min(floor(epoch(ts))) AS xmin, min(round(value * 100)) AS ymin, max(floor(epoch(ts))) AS xmax, max(round(value * 100)) AS ymax
  FROM events GROUP BY user_id, CAST(ts AS DATE), day(ts)"""
LINE = """SELECT id, min(cx - hx) AS xmin, min(cy - hy) AS ymin, max(cx + hx) AS xmax, max(cy + hy) AS ymax FROM (
  SELECT ((l_orderkey * 8 + l_linenumber) * 100000 + l_partkey) * 10000 + l_suppkey AS id,
    CAST(date_diff('day', DATE '1995-01-01', CAST(l_shipdate AS DATE)) * 1000 AS DOUBLE) AS cx, CAST(floor(round(l_extendedprice * 100) / 4) AS DOUBLE) AS cy,
    CAST(l_quantity * 10 AS DOUBLE) AS hx, CAST(round(l_discount * 100) * 500 AS DOUBLE) AS hy FROM lineitem) GROUP BY id"""
FIXTURES = {"even": EVEN, "skew": SKEW, "skew_wide": SKEW_WIDE, "span": SPAN, "line": LINE}
U = "u AS (SELECT min(xmin) AS x0, min(ymin) AS y0, max(xmax) AS x1, max(ymax) AS y1, count(*) AS n FROM b)"


def base(fixture: str) -> str:
    return f"b AS MATERIALIZED ({FIXTURES[fixture]}), {U}"


def universe(fixture: str) -> str:
    return f"WITH {base(fixture)} SELECT x0 AS xmin, y0 AS ymin, x1 AS xmax, y1 AS ymax, n FROM u"


# Layouts: a chain of CTEs that ends in t (tile_id, xmin, ymin, xmax, ymax, planned).


def grid_xy(mx: int, my: int) -> str:
    """Cells of unlike numbers on the two axes."""
    return f"""g AS (SELECT u.*, x1 - x0 AS w, y1 - y0 AS h FROM u),
t AS (SELECT CAST(j * {mx} + i AS INTEGER) AS tile_id, x0 + w * i / {mx} AS xmin, y0 + h * j / {my} AS ymin,
  CASE WHEN i = {mx - 1} THEN x1 ELSE x0 + w * (i + 1) / {mx} END AS xmax, CASE WHEN j = {my - 1} THEN y1 ELSE y0 + h * (j + 1) / {my} END AS ymax, CAST(NULL AS BIGINT) AS planned
  FROM (SELECT *, unnest(range({mx})) AS i FROM (SELECT *, unnest(range({my})) AS j FROM g)))"""


def grid(payload: int | None = None, cells: int | None = None) -> str:
    m = f"CAST({cells} AS BIGINT)" if cells else f"CAST(ceil(sqrt(n / CAST({payload} AS DOUBLE))) AS BIGINT)"
    return f"""g AS (SELECT u.*, {m} AS m, x1 - x0 AS w, y1 - y0 AS h FROM u),
t AS (SELECT CAST(j * m + i AS INTEGER) AS tile_id, x0 + w * i / m AS xmin, y0 + h * j / m AS ymin,
  CASE WHEN i = m - 1 THEN x1 ELSE x0 + w * (i + 1) / m END AS xmax, CASE WHEN j = m - 1 THEN y1 ELSE y0 + h * (j + 1) / m END AS ymax, CAST(NULL AS BIGINT) AS planned
  FROM (SELECT *, unnest(range(m)) AS i FROM (SELECT *, unnest(range(m)) AS j FROM g)))"""


GRID_ROUTED = """a AS (SELECT b.id, CAST(j * m + i AS INTEGER) AS tile_id FROM (
  SELECT *, unnest(range(i0, i1 + 1)) AS i FROM (SELECT *, unnest(range(j0, j1 + 1)) AS j FROM (
    SELECT b.id, m, greatest(0, least(m - 1, CAST(floor((xmin - x0) * m / w) AS BIGINT))) AS i0, greatest(0, least(m - 1, CAST(floor((xmax - x0) * m / w) AS BIGINT))) AS i1,
      greatest(0, least(m - 1, CAST(floor((ymin - y0) * m / h) AS BIGINT))) AS j0, greatest(0, least(m - 1, CAST(floor((ymax - y0) * m / h) AS BIGINT))) AS j1 FROM b, g))) b)"""
ROUTED = """a AS (SELECT b.id, t.tile_id FROM b, t, u WHERE (b.xmin < t.xmax OR t.xmax >= u.x1) AND (b.ymin < t.ymax OR t.ymax >= u.y1) AND b.xmax >= t.xmin AND b.ymax >= t.ymin)"""
ROUTED_CLOSED = """a AS (SELECT b.id, t.tile_id FROM b, t WHERE b.xmin <= t.xmax AND b.ymin <= t.ymax AND b.xmax >= t.xmin AND b.ymax >= t.ymin)"""
LOADS = "p AS (SELECT t.tile_id, count(a.id) AS payload FROM t LEFT JOIN a USING (tile_id) GROUP BY 1)"
QUALITY = """SELECT count(*) AS k, (SELECT n FROM u) AS objects, CAST(sum(payload) AS BIGINT) AS total, round(sum(payload) / (SELECT n FROM u) - 1, 6) AS lambda,
  round(stddev_pop(payload), 6) AS sigma, max(payload) AS largest, round(max(payload) / avg(payload), 6) AS largest_to_mean, count(*) FILTER (payload = 0) AS empty FROM p"""
TILES = "SELECT tile_id, xmin, ymin, xmax, ymax, planned FROM t"


def strip(payload: int, axis: str = "x", count: str = "live") -> str:
    o = "y" if axis == "x" else "x"
    gone = f"{axis}max < c" if count == "live" else f"({axis}min + {axis}max) / 2 < c"
    cut_tile = f"lo AS {axis}min, {o}0 AS {o}min, hi AS {axis}max, {o}1 AS {o}max"
    return f"""cum AS MATERIALIZED (SELECT c, sum(n) OVER (ORDER BY c) AS le FROM (SELECT ({axis}min + {axis}max) / 2 AS c, count(*) AS n FROM b GROUP BY 1)),
gone AS MATERIALIZED (SELECT c, coalesce(max(before), 0) AS gone FROM (
  SELECT c, CAST(NULL AS BIGINT) AS before FROM cum UNION ALL SELECT cum.c, f.le FROM cum ASOF JOIN (
    SELECT v, sum(n) OVER (ORDER BY v) AS le FROM (SELECT {f"{axis}max" if count == "live" else f"({axis}min + {axis}max) / 2"} AS v, count(*) AS n FROM b GROUP BY 1)) f ON cum.c > f.v) GROUP BY c),
nxt AS MATERIALIZED (SELECT gone.c, greatest_next.c AS nxt FROM gone, LATERAL (SELECT min(z.c) AS c FROM cum z WHERE z.c > gone.c AND z.le > gone.gone + {payload}) greatest_next),
cuts AS (SELECT min(c) AS c FROM cum WHERE le > {payload} UNION ALL SELECT nxt.nxt FROM cuts JOIN nxt ON cuts.c = nxt.c WHERE nxt.nxt IS NOT NULL),
kept AS (SELECT c FROM cuts, u WHERE c > {axis}0 AND c < {axis}1),
t AS (SELECT CAST(row_number() OVER (ORDER BY lo) - 1 AS INTEGER) AS tile_id, {cut_tile}, CAST(NULL AS BIGINT) AS planned FROM (
  SELECT lo, coalesce(lead(lo) OVER (ORDER BY lo), (SELECT {axis}1 FROM u)) AS hi FROM (SELECT {axis}0 AS lo FROM u UNION ALL SELECT c FROM kept)), u)"""


def least_cut(payload: int, steps: int) -> str:
    parts = ["s0 AS (SELECT x0 AS ax, y0 AS ay, FALSE AS done FROM u)"]
    for i in range(steps):
        parts.append(f"""v{i} AS MATERIALIZED (SELECT b.* FROM b, s{i} s WHERE NOT s.done AND b.xmax >= s.ax AND b.ymax >= s.ay),
m{i} AS MATERIALIZED (SELECT count(*) AS n, list_sort(list((v.xmin + v.xmax) / 2))[{payload + 1}] AS qx, list_sort(list((v.ymin + v.ymax) / 2))[{payload + 1}] AS qy,
  min((v.xmin + v.xmax) / 2) FILTER ((v.xmin + v.xmax) / 2 > s.ax) AS nx, min((v.ymin + v.ymax) / 2) FILTER ((v.ymin + v.ymax) / 2 > s.ay) AS ny FROM v{i} v, s{i} s),
c{i} AS MATERIALIZED (SELECT n, CASE WHEN n > {payload} THEN CASE WHEN qx > s.ax THEN qx ELSE nx END END AS cx, CASE WHEN n > {payload} THEN CASE WHEN qy > s.ay THEN qy ELSE ny END END AS cy FROM m{i}, s{i} s),
k{i} AS MATERIALIZED (SELECT count(*) FILTER (v.xmin < c.cx AND c.cx <= v.xmax) AS kx, count(*) FILTER (v.ymin < c.cy AND c.cy <= v.ymax) AS ky,
  count(*) FILTER ((v.xmin + v.xmax) / 2 < c.cx) AS px, count(*) FILTER ((v.ymin + v.ymax) / 2 < c.cy) AS py FROM v{i} v, c{i} c),
d{i} AS MATERIALIZED (SELECT s.ax, s.ay, s.done, c.*, k.*, CASE WHEN c.cx IS NULL AND c.cy IS NULL THEN NULL WHEN c.cy IS NULL OR (c.cx IS NOT NULL AND k.kx <= k.ky) THEN 'x' ELSE 'y' END AS axis FROM s{i} s, c{i} c, k{i} k),
s{i + 1} AS MATERIALIZED (SELECT CASE WHEN axis = 'x' THEN cx ELSE ax END AS ax, CASE WHEN axis = 'y' THEN cy ELSE ay END AS ay, done OR axis IS NULL AS done FROM d{i})""")
    rows = " UNION ALL ".join(
        f"SELECT {i} AS i, ax AS xmin, ay AS ymin, CASE WHEN axis = 'x' THEN cx ELSE x1 END AS xmax, CASE WHEN axis = 'y' THEN cy ELSE y1 END AS ymax, CASE axis WHEN 'x' THEN px WHEN 'y' THEN py ELSE d{i}.n END AS planned FROM d{i}, u WHERE NOT done"
        for i in range(steps)
    )
    return ",\n".join(parts) + f",\nt AS (SELECT CAST(i AS INTEGER) AS tile_id, xmin, ymin, xmax, ymax, planned FROM ({rows}))"


def binary(payload: int, levels: int, cut: str = "median") -> str:
    parts = [
        "o0 AS MATERIALIZED (SELECT *, CAST(1 AS BIGINT) AS node FROM b)",
        "r0 AS MATERIALIZED (SELECT CAST(1 AS BIGINT) AS node, x0, y0, x1, y1 FROM u)",
    ]
    mid = "quantile_disc((xmin + xmax) / 2, 0.5) AS mx, quantile_disc((ymin + ymax) / 2, 0.5) AS my" if cut == "median" else "NULL AS mx, NULL AS my"
    for i in range(levels):
        at = ("st.mx", "st.my") if cut == "median" else ("(r.x0 + r.x1) / 2", "(r.y0 + r.y1) / 2")
        parts.append(f"""st{i} AS MATERIALIZED (SELECT node, count(*) AS n, {mid} FROM o{i} GROUP BY node),
f{i} AS MATERIALIZED (SELECT r.*, st.n, {at[0]} AS mx, {at[1]} AS my, CASE WHEN {at[0]} > x0 AND {at[0]} < x1 THEN ({at[0]} - x0) / (x1 - x0) END AS fx, CASE WHEN {at[1]} > y0 AND {at[1]} < y1 THEN ({at[1]} - y0) / (y1 - y0) END AS fy FROM r{i} r JOIN st{i} st USING (node)),
ch{i} AS MATERIALIZED (SELECT *, CASE WHEN n <= {payload} OR (fx IS NULL AND fy IS NULL) THEN NULL WHEN fy IS NULL OR (fx IS NOT NULL AND fx * (1 - fx) >= fy * (1 - fy)) THEN 'x' ELSE 'y' END AS axis FROM f{i}),
pt{i} AS MATERIALIZED (SELECT ch.node, count(*) FILTER (CASE axis WHEN 'x' THEN xmin < mx ELSE ymin < my END) AS l, count(*) FILTER (CASE axis WHEN 'x' THEN xmax >= mx ELSE ymax >= my END) AS g FROM ch{i} ch JOIN o{i} o USING (node) WHERE axis IS NOT NULL GROUP BY 1),
sp{i} AS MATERIALIZED (SELECT ch.* FROM ch{i} ch JOIN pt{i} pt USING (node) WHERE l > 0 AND g > 0 AND NOT (l = n AND g = n)),
r{i + 1} AS MATERIALIZED (SELECT node * 2 AS node, x0, y0, CASE axis WHEN 'x' THEN mx ELSE x1 END AS x1, CASE axis WHEN 'x' THEN y1 ELSE my END AS y1 FROM sp{i}
  UNION ALL SELECT node * 2 + 1, CASE axis WHEN 'x' THEN mx ELSE x0 END, CASE axis WHEN 'x' THEN y0 ELSE my END, x1, y1 FROM sp{i}),
o{i + 1} AS MATERIALIZED (SELECT o.* EXCLUDE (node), node * 2 AS node FROM o{i} o JOIN sp{i} sp USING (node) WHERE CASE axis WHEN 'x' THEN xmin < mx ELSE ymin < my END
  UNION ALL SELECT o.* EXCLUDE (node), node * 2 + 1 AS node FROM o{i} o JOIN sp{i} sp USING (node) WHERE CASE axis WHEN 'x' THEN xmax >= mx ELSE ymax >= my END)""")
    leaves = " UNION ALL ".join(f"SELECT x0, y0, x1, y1, n FROM ch{i} WHERE node NOT IN (SELECT node FROM sp{i})" for i in range(levels))
    return ",\n".join(parts) + f",\nt AS (SELECT CAST(row_number() OVER (ORDER BY x0, y0, x1, y1) - 1 AS INTEGER) AS tile_id, x0 AS xmin, y0 AS ymin, x1 AS xmax, y1 AS ymax, n AS planned FROM ({leaves}))"


def quad(payload: int, levels: int) -> str:
    parts = ["o0 AS MATERIALIZED (SELECT *, CAST(0 AS BIGINT) AS node FROM b)", "r0 AS MATERIALIZED (SELECT CAST(0 AS BIGINT) AS node, x0, y0, x1, y1 FROM u)"]
    for i in range(levels):
        q = [("x0", "y0", "mx", "my"), ("mx", "y0", "x1", "my"), ("x0", "my", "mx", "y1"), ("mx", "my", "x1", "y1")]
        w = ["xmin < mx AND ymin < my", "xmax >= mx AND ymin < my", "xmin < mx AND ymax >= my", "xmax >= mx AND ymax >= my"]
        kids = " UNION ALL ".join(f"SELECT node * 4 + {j} AS node, {a} AS x0, {c} AS y0, {d} AS x1, {e} AS y1 FROM sp{i}" for j, (a, c, d, e) in enumerate(q))
        objs = " UNION ALL ".join(f"SELECT o.* EXCLUDE (node), node * 4 + {j} AS node FROM o{i} o JOIN sp{i} sp USING (node) WHERE {x}" for j, x in enumerate(w))
        parts.append(f"""n{i} AS MATERIALIZED (SELECT r.*, (x0 + x1) / 2 AS mx, (y0 + y1) / 2 AS my, coalesce(c.n, 0) AS n FROM r{i} r LEFT JOIN (SELECT node, count(*) AS n FROM o{i} GROUP BY node) c USING (node)),
sp{i} AS MATERIALIZED (SELECT * FROM n{i} WHERE n > {payload}),
r{i + 1} AS MATERIALIZED ({kids}),
o{i + 1} AS MATERIALIZED ({objs})""")
    leaves = " UNION ALL ".join(f"SELECT x0, y0, x1, y1, n FROM n{i} WHERE n <= {payload}" for i in range(levels))
    return ",\n".join(parts) + f",\nt AS (SELECT CAST(row_number() OVER (ORDER BY x0, y0, x1, y1) - 1 AS INTEGER) AS tile_id, x0 AS xmin, y0 AS ymin, x1 AS xmax, y1 AS ymax, n AS planned FROM ({leaves}))"


def curve_key(curve: str, order: int = 16) -> str:
    side = 1 << order
    q = f"""SELECT b.*, greatest(0, least({side - 1}, CAST(floor(((xmin + xmax) / 2 - x0) * {side}.0 / (x1 - x0)) AS BIGINT))) AS hx,
      greatest(0, least({side - 1}, CAST(floor(((ymin + ymax) / 2 - y0) * {side}.0 / (y1 - y0)) AS BIGINT))) AS hy, CAST(0 AS BIGINT) AS key FROM b, u"""
    if curve == "hilbert":
        for k in range(order - 1, -1, -1):
            low = (1 << k) - 1
            bx, by, lx, ly = f"((hx >> {k}) & 1)", f"((hy >> {k}) & 1)", f"(hx & {low})", f"(hy & {low})"
            q = f"""SELECT * REPLACE (key * 4 + CASE WHEN {bx} = 0 THEN {by} ELSE 3 - {by} END AS key,
              CASE WHEN {by} = 1 THEN {lx} WHEN {bx} = 1 THEN {low} - {ly} ELSE {ly} END AS hx, CASE WHEN {by} = 1 THEN {ly} WHEN {bx} = 1 THEN {low} - {lx} ELSE {lx} END AS hy) FROM ({q})"""
        return q
    bits = " + ".join(f"(((hx >> {k}) & 1) * 2 + ((hy >> {k}) & 1)) * {4**k}" for k in range(order))
    q = f"SELECT * REPLACE ({bits} AS key) FROM ({q})"
    if curve == "gray":
        s = 1
        while s < 2 * order:
            q = f"SELECT * REPLACE (xor(key, key >> {s}) AS key) FROM ({q})"
            s *= 2
    return q


def curve_pack(payload: int, curve: str = "hilbert", order: int = 16) -> str:
    return f"""k AS MATERIALIZED ({curve_key(curve, order)}),
t AS (SELECT CAST(home AS INTEGER) AS tile_id, min(xmin) AS xmin, min(ymin) AS ymin, max(xmax) AS xmax, max(ymax) AS ymax, count(*) AS planned
  FROM (SELECT *, (row_number() OVER (ORDER BY key, id) - 1) // {payload} AS home FROM k) GROUP BY home)"""


def sort_tile(payload: int, edges: str = "tight") -> str:
    members = f"""q AS MATERIALIZED (SELECT *, (row_number() OVER (PARTITION BY slab ORDER BY cy, id) - 1) // {payload} AS tile FROM (
  SELECT *, (row_number() OVER (ORDER BY cx, id) - 1) // CAST(ceil(sqrt((SELECT n FROM u) / CAST({payload} AS DOUBLE))) * {payload} AS BIGINT) AS slab FROM (SELECT *, (xmin + xmax) / 2 AS cx, (ymin + ymax) / 2 AS cy FROM b)))"""
    if edges == "tight":
        return f"""{members},
t AS (SELECT CAST(slab * (CAST(ceil(sqrt((SELECT n FROM u) / CAST({payload} AS DOUBLE))) AS BIGINT) + 1) + tile AS INTEGER) AS tile_id, min(xmin) AS xmin, min(ymin) AS ymin, max(xmax) AS xmax, max(ymax) AS ymax, count(*) AS planned FROM q GROUP BY slab, tile)"""
    return f"""{members},
e AS (SELECT slab, tile, min(cx) AS cx, min(cy) AS cy, count(*) AS n FROM q GROUP BY 1, 2),
sl AS (SELECT slab, min(cx) AS cx FROM e GROUP BY 1),
sx AS (SELECT slab, CASE WHEN slab = 0 THEN x0 ELSE cx END AS lo, coalesce(lead(cx) OVER (ORDER BY slab), x1) AS hi FROM sl, u),
t AS (SELECT CAST(row_number() OVER (ORDER BY slab, tile) - 1 AS INTEGER) AS tile_id, * EXCLUDE (slab, tile) FROM (
  SELECT slab, tile, lo AS xmin, CASE WHEN tile = 0 THEN y0 ELSE cy END AS ymin, hi AS xmax, coalesce(lead(cy) OVER (PARTITION BY slab ORDER BY tile), y1) AS ymax, e.n AS planned FROM e JOIN sx USING (slab), u)
  WHERE xmin < xmax AND ymin < ymax)"""


def sort_tile_even(payload: int) -> str:
    """Ranks parted evenly into slabs, and those evenly into tiles."""
    m = f"CAST(ceil(sqrt((SELECT n FROM u) / {payload}.0)) AS BIGINT)"
    per = f"CAST(ceil((SELECT n FROM u) / CAST({m} AS DOUBLE)) AS BIGINT)"
    each = f"CAST(ceil({per} / CAST({m} AS DOUBLE)) AS BIGINT)"
    return f"""q AS MATERIALIZED (SELECT *, (row_number() OVER (PARTITION BY slab ORDER BY cy, id) - 1) // {each} AS tile FROM (
  SELECT *, (row_number() OVER (ORDER BY cx, id) - 1) // {per} AS slab FROM (SELECT *, (xmin + xmax) / 2 AS cx, (ymin + ymax) / 2 AS cy FROM b))),
t AS (SELECT CAST(slab * ({m} + 1) + tile AS INTEGER) AS tile_id, min(xmin) AS xmin, min(ymin) AS ymin, max(xmax) AS xmax, max(ymax) AS ymax, count(*) AS planned FROM q GROUP BY slab, tile)"""


def sort_tile_in_buckets(payload: int, cuts: list[float]) -> str:
    """Sort-tile inside the slabs between fixed anchors."""
    bucket = " + ".join(f"CAST(cx >= {c!r} AS INTEGER)" for c in cuts)
    return f"""k AS MATERIALIZED (SELECT *, count(*) OVER (PARTITION BY bucket) AS nb FROM (SELECT *, {bucket} AS bucket FROM (SELECT *, (xmin + xmax) / 2 AS cx, (ymin + ymax) / 2 AS cy FROM b))),
q AS MATERIALIZED (SELECT *, (row_number() OVER (PARTITION BY bucket, slab ORDER BY cy, rx) - 1) // {payload} AS tile FROM (
  SELECT *, (rx - 1) // CAST(ceil(sqrt(nb / {payload}.0)) * {payload} AS BIGINT) AS slab FROM (SELECT *, row_number() OVER (PARTITION BY bucket ORDER BY cx, id) AS rx FROM k))),
t AS (SELECT CAST(row_number() OVER (ORDER BY bucket, xmin, ymin, xmax, ymax) - 1 AS INTEGER) AS tile_id, * EXCLUDE (bucket) FROM (
  SELECT bucket, min(xmin) AS xmin, min(ymin) AS ymin, max(xmax) AS xmax, max(ymax) AS ymax, count(*) AS planned FROM q GROUP BY bucket, slab, tile))"""


def sampled_base(fixture: str, every: int) -> str:
    """fb: all boxes; b: those of ids divisible by `every`; u: the universe of all with the sample's size."""
    return f"""fb AS MATERIALIZED ({FIXTURES[fixture]}), b AS MATERIALIZED (SELECT * FROM fb WHERE id % {every} = 0),
u AS (SELECT min(xmin) AS x0, min(ymin) AS y0, max(xmax) AS x1, max(ymax) AS y1, (SELECT count(*) FROM b) AS n FROM fb)"""


def scaled(payload: int) -> str:
    """The payload of a sample, in the sample's own measure."""
    return f"(SELECT greatest(1, CAST(round({payload}.0 * (SELECT count(*) FROM b) / (SELECT count(*) FROM fb)) AS BIGINT)))"


ROUTED_ALL = ROUTED.replace("FROM b, t, u", "FROM fb b, t, u")
QUALITY_ALL = QUALITY.replace("(SELECT n FROM u)", "(SELECT count(*) FROM fb)")


def tiles(fixture: str, layout: str) -> str:
    return f"WITH RECURSIVE {base(fixture)}, {layout} {TILES}"


def quality(fixture: str, layout: str, routed: str = ROUTED) -> str:
    return f"WITH RECURSIVE {base(fixture)}, {layout}, {routed}, {LOADS} {QUALITY}"


MEET = "r.xmin <= s.xmax AND r.xmax >= s.xmin AND r.ymin <= s.ymax AND r.ymax >= s.ymin"
CONTAINS = "r.xmin <= s.xmin AND r.xmax >= s.xmax AND r.ymin <= s.ymin AND r.ymax >= s.ymax"


def within_distance(d: float) -> str:
    dx, dy = (f"greatest(0, r.{a}min - s.{a}max, s.{a}min - r.{a}max)" for a in "xy")
    return f"{dx} * {dx} + {dy} * {dy} <= {d * d}"


def join(fixture: str, test: str = MEET, r: str = "id % 2 = 0", s: str = "id % 2 = 1") -> str:
    return f"WITH b AS MATERIALIZED ({FIXTURES[fixture]}) SELECT r.id AS r_id, s.id AS s_id FROM (SELECT * FROM b WHERE {r}) r JOIN (SELECT * FROM b WHERE {s}) s ON {test}"


def self_join(fixture: str) -> str:
    return f"WITH b AS MATERIALIZED ({FIXTURES[fixture]}) SELECT r.id AS r_id, s.id AS s_id FROM b r JOIN b s ON r.id < s.id AND {MEET}"
