"""DuckDB SQL for the queries: point sets, pairs, weights and surfaces."""

from __future__ import annotations

import math

from stkfun.config import HOUR, W_EMBED, W_EVENTS, W_LINES, W_ORDERS, DistanceGrid, StudyWindow


def uniform(tag: str, key: str) -> str:
    return f"(CAST(('0x' || substr(md5('{tag}:' || {key}), 1, 8)) AS BIGINT) / 4294967296.0::DOUBLE)"


def uniform_point(w: StudyWindow, key: str) -> str:
    return f"{w.x0}::DOUBLE + {w.x1 - w.x0}::DOUBLE * {uniform('x', key)} AS x, {w.y0}::DOUBLE + {w.y1 - w.y0}::DOUBLE * {uniform('y', key)} AS y, {w.t_start} + CAST(floor({float(w.period)}::DOUBLE * {uniform('t', key)}) AS BIGINT) AS t0"


POINTS = {
    "events_skewed": "SELECT event_id AS id, value::DOUBLE AS x, CAST(json_extract_string(props, '$.k') AS DOUBLE) AS y, epoch_us(ts) AS t0, event_type AS mark, 1 AS mult FROM events",
    "events_uniform": f"SELECT event_id AS id, {uniform_point(W_EVENTS, 'event_id')}, event_type AS mark, 1 AS mult FROM events",
    "orders_month": "SELECT o_orderkey AS id, o_totalprice::DOUBLE / 5000 AS x, (c_acctbal::DOUBLE + 1000) / 110 AS y, epoch_us(o_orderdate::TIMESTAMP) AS t0, o_orderpriority AS mark, 1 AS mult, c_nationkey AS zone FROM orders JOIN customer ON o_custkey = c_custkey",
    "lineitem_grid": "SELECT (CAST(t0 / 86400000000 AS BIGINT) * 1000 + CAST(x AS BIGINT)) * 100 + CAST(y AS BIGINT) AS id, x, y, t0, NULL AS mark, n AS mult FROM (SELECT l_quantity::DOUBLE AS x, round(l_discount::DOUBLE * 100) AS y, epoch_us(l_shipdate::TIMESTAMP) AS t0, count(*) AS n FROM lineitem GROUP BY ALL)",
    "embedding_plane": "SELECT vec_id AS id, embedding[1]::DOUBLE AS x, embedding[2]::DOUBLE AS y, 0::BIGINT AS t0, label AS mark, 1 AS mult FROM embeddings",
}
WINDOWS = {"events_skewed": W_EVENTS, "events_uniform": W_EVENTS, "orders_month": W_ORDERS, "lineitem_grid": W_LINES, "embedding_plane": W_EMBED}


def pts(name: str, where: str = "") -> str:
    return f"pts AS (SELECT * FROM ({POINTS[name]}){' WHERE ' + where if where else ''})"


_D = "sqrt((c.x - q.x) * (c.x - q.x) + (c.y - q.y) * (c.y - q.y))"


def pairs(s: float, t: int, extra: str = "", on: str = "", source: str = "pts") -> str:
    """A CTE named pairs over pts: a range join in time and x."""
    return f"""pairs AS (SELECT c.id AS i, q.id AS j, c.x, c.y, c.t0, {_D} AS d, abs(c.t0 - q.t0) AS u, q.x - c.x AS dx, q.y - c.y AS dy, c.mult AS c_mult, q.mult AS q_mult, c.mark AS c_mark, q.mark AS q_mark{extra}
  FROM {source} c JOIN {source} q ON q.t0 BETWEEN c.t0 - {t} AND c.t0 + {t} AND c.id <> q.id{on} WHERE {_D} <= {s})"""


def lattice_pairs(t: int) -> str:
    """The same for integer places within 1, by offsets."""
    return f"""pairs AS (SELECT c.id AS i, q.id AS j, c.x, c.y, c.t0, {_D} AS d, abs(c.t0 - q.t0) AS u, c.mult AS c_mult, q.mult AS q_mult
  FROM (SELECT *, x + ox AS kx, y + oy AS ky FROM pts, (VALUES (0, 0), (1, 0), (-1, 0), (0, 1), (0, -1)) o(ox, oy)) c
  JOIN pts q ON q.x = c.kx AND q.y = c.ky AND q.t0 BETWEEN c.t0 - {t} AND c.t0 + {t} AND c.id <> q.id)"""


def w_rect(w: StudyWindow, x="x", y="y", d="d") -> str:
    a = {k: f"acos(least(1.0::DOUBLE, ({g}) / {d}))" for k, g in (("l", f"{x} - {w.x0}::DOUBLE"), ("r", f"{w.x1}::DOUBLE - {x}"), ("b", f"{y} - {w.y0}::DOUBLE"), ("t", f"{w.y1}::DOUBLE - {y}"))}
    lost = " + ".join(f"least({math.pi / 2!r}::DOUBLE, {a[h]} + {a[v]})" for h, v in (("l", "b"), ("l", "t"), ("r", "b"), ("r", "t")))
    return f"CASE WHEN {d} <= 0 THEN 1.0::DOUBLE ELSE 1.0::DOUBLE / (1.0::DOUBLE - ({lost}) / {2 * math.pi!r}::DOUBLE) END"


def w_time(w: StudyWindow, t="t0", u="u") -> str:
    return f"CASE WHEN {t} - {u} >= {w.t_start} AND {t} + {u} <= {w.t_end} THEN 1.0::DOUBLE ELSE 2.0::DOUBLE END"


def ring_weights(ring, source: str, name: str = "rw") -> str:
    """CTEs that end in ``name`` (id, w): the weights of circles (id, x, y, d) of ``source``
    in a simple polygon, by sorting each circle's crossings and testing its arcs."""
    edges = ", ".join(f"({a[0]!r}::DOUBLE, {a[1]!r}::DOUBLE, {b[0]!r}::DOUBLE, {b[1]!r}::DOUBLE)" for a, b in zip(ring, [*ring[1:], ring[0]]))
    full = f"{2 * math.pi!r}::DOUBLE"
    return f"""edges AS (SELECT * FROM (VALUES {edges}) e(ax, ay, ex, ey)),
meet AS (SELECT id, x, y, d, ax, ay, ex - ax AS sx, ey - ay AS sy, (ax - x) * (ex - ax) + (ay - y) * (ey - ay) AS half, (ex - ax) * (ex - ax) + (ey - ay) * (ey - ay) AS size2 FROM {source}, edges WHERE d > 0),
cut AS (SELECT *, half * half - size2 * ((ax - x) * (ax - x) + (ay - y) * (ay - y) - d * d) AS disc FROM meet),
crossing AS (SELECT id, x, y, d, atan2(ay - y + k * sy, ax - x + k * sx) AS ang FROM (SELECT *, (sg * sqrt(disc) - half) / size2 AS k FROM cut, (VALUES (-1), (1)) z(sg) WHERE disc > 0) WHERE k BETWEEN 0 AND 1),
arcs AS (SELECT id, x, y, d, ang, coalesce(lead(ang) OVER (PARTITION BY id ORDER BY ang), min(ang) OVER (PARTITION BY id) + {full}) - ang AS arc FROM crossing),
mids AS MATERIALIZED (SELECT id, row_number() OVER () AS k, arc, x + d * cos(ang + arc / 2) AS mx, y + d * sin(ang + arc / 2) AS my FROM arcs WHERE arc > 0.000000000001),
odd AS (SELECT k, count(*) AS n FROM mids, edges WHERE (ay > my) <> (ey > my) AND mx < (ex - ax) * (my - ay) / (ey - ay) + ax GROUP BY k),
share AS (SELECT id, sum(CASE WHEN n % 2 = 1 THEN arc ELSE 0 END) / {full} AS f FROM mids LEFT JOIN odd USING (k) GROUP BY id),
{name} AS (SELECT s.id, CASE WHEN f IS NULL THEN 1.0::DOUBLE ELSE 1.0::DOUBLE / f END AS w FROM {source} s LEFT JOIN share USING (id))"""


def inside(ring) -> str:
    """Whether (x, y) lies in the ring, by the even-odd rule."""
    crossings = " + ".join(f"CASE WHEN ({a[1]!r}::DOUBLE > y) <> ({b[1]!r}::DOUBLE > y) AND x < {b[0] - a[0]!r}::DOUBLE * (y - {a[1]!r}::DOUBLE) / {b[1] - a[1]!r}::DOUBLE + {a[0]!r}::DOUBLE THEN 1 ELSE 0 END" for a, b in zip(ring, [*ring[1:], ring[0]]) if a[1] != b[1])
    return f"({crossings}) % 2 = 1"


def weight(w: StudyWindow, correction: str = "isotropic") -> str:
    if correction == "none":
        return "1.0::DOUBLE"
    if correction == "translation":
        a, b, p = w.x1 - w.x0, w.y1 - w.y0, float(w.period)
        return f"({a * b}::DOUBLE / (({a}::DOUBLE - abs(dx)) * ({b}::DOUBLE - abs(dy)))) * ({p}::DOUBLE / ({p}::DOUBLE - u))"
    return f"({w_rect(w)}) * ({w_time(w)})"


def bins(g: DistanceGrid, w: str, times: str = "1", keys: str = "", where: str = "") -> str:
    """hist: pairs and fixed-point weight of each bin of the CTE pairs."""
    k = f"{keys}, " if keys else ""
    return f"""binned AS (SELECT {k}CAST(ceil(d / {g.s_step}::DOUBLE) AS INTEGER) AS si, CAST((u + {g.t_step - 1}) // {g.t_step} AS INTEGER) AS ti, {times} AS m, CAST(round(({w}) * 1000000000) AS BIGINT) AS w FROM pairs{' WHERE ' + where if where else ''}),
hist AS (SELECT {k}si, ti, CAST(sum(m) AS BIGINT) AS pairs, CAST(sum(w * m) AS BIGINT) AS wfix FROM binned WHERE si <= {g.s_steps} AND ti <= {g.t_steps} GROUP BY {k}si, ti)"""


def cumulated(g: DistanceGrid, keys: str = "", groups: str = "", hist: str = "hist") -> str:
    k, p = (f"{keys}, ", f"{keys}, ") if keys else ("", "")
    base = f"({groups}) AS gr, " if keys else ""
    on = f"h.{keys} = dense.{keys} AND " if keys else ""
    dk = f"dense.{keys}, " if keys else ""
    return f"""dense AS (SELECT {k}CAST(a AS INTEGER) AS si, CAST(b AS INTEGER) AS ti FROM {base}range({g.s_steps + 1}) s(a), range({g.t_steps + 1}) t(b)),
full_ AS (SELECT {dk}dense.si, dense.ti, coalesce(h.pairs, 0) AS pairs, coalesce(h.wfix, 0) AS wfix FROM dense LEFT JOIN {hist} h ON {on}h.si = dense.si AND h.ti = dense.ti),
cum AS (SELECT {k}si, ti, CAST(sum(p1) OVER (PARTITION BY {p}si ORDER BY ti) AS BIGINT) AS pairs, CAST(sum(w1) OVER (PARTITION BY {p}si ORDER BY ti) AS BIGINT) AS wfix FROM
  (SELECT {k}si, ti, sum(pairs) OVER (PARTITION BY {p}ti ORDER BY si) AS p1, sum(wfix) OVER (PARTITION BY {p}ti ORDER BY si) AS w1 FROM full_))"""


def l_of(k: str, s: str, t: str) -> str:
    return f"sqrt(({k}) / ({2 * math.pi!r}::DOUBLE * ({t}))) - ({s})"


def scale_of(w: StudyWindow, n: str) -> str:
    return f"{w.area * w.hours!r}::DOUBLE / {n}::DOUBLE"


def surface(g: DistanceGrid, scale: str, keys: str = "", join: str = "") -> str:
    """The final SELECT: si, ti, s, t, pairs, and K and L to 4 decimals."""
    k = f"{keys}, " if keys else ""
    kk = f"({scale}) * (wfix / 1000000000.0::DOUBLE)"
    return f"SELECT {k}si, ti, si * {float(g.s_step)}::DOUBLE AS s, ti * {g.t_step / HOUR}::DOUBLE AS t, pairs, round({kk}, 4) AS k, round({l_of(kk, f'si * {float(g.s_step)}::DOUBLE', f'ti * {g.t_step / HOUR}::DOUBLE')}, 4) AS l FROM cum{join} WHERE si > 0 AND ti > 0"


N = ", (SELECT count(*) AS n FROM pts) nn"


def k_surface(name: str, g: DistanceGrid, correction: str = "isotropic") -> str:
    w = WINDOWS[name]
    return f"WITH {pts(name)}, {pairs(g.s_max, g.t_max)}, {bins(g, weight(w, correction))}, {cumulated(g)} {surface(g, scale_of(w, '(n * (n - 1))'), join=N)}"


def pair_bins(name: str, g: DistanceGrid) -> str:
    """Pair counts of each bin, the shared check of all pair variants."""
    return f"WITH {pts(name)}, {pairs(g.s_max, g.t_max)}, {bins(g, '1.0::DOUBLE')} SELECT si, ti, pairs FROM hist"
