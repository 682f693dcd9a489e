"""DuckDB SQL for the queries SQL can express, built from one chain of common table expressions."""

from __future__ import annotations

import math

SHRINK = repr(math.cos(math.radians(48.8566)))
CROSS = "((b.x - a.x) * (r.y - a.y) - (b.y - a.y) * (r.x - a.x))"

CHAIN: list[tuple[str, str]] = [
    ("trace", """
        SELECT user_id % 20 AS session_id, event_id AS sample_id,
          CASE event_type WHEN 'click' THEN -300.0::DOUBLE WHEN 'view' THEN 300.0::DOUBLE WHEN 'purchase' THEN 0.0::DOUBLE WHEN 'signup' THEN -250.0::DOUBLE WHEN 'error' THEN 250.0::DOUBLE END
            + CAST(CAST(json_extract_string(props, '$.k') AS BIGINT) - 50 AS DOUBLE) * 1.2::DOUBLE AS x,
          CASE event_type WHEN 'click' THEN -200.0::DOUBLE WHEN 'view' THEN -200.0::DOUBLE WHEN 'purchase' THEN 0.0::DOUBLE WHEN 'signup' THEN 200.0::DOUBLE WHEN 'error' THEN 200.0::DOUBLE END
            + least(value, 120.0::DOUBLE) - 35.0::DOUBLE AS y,
          epoch_us(ts) // 1000 - 1704067200000 AS t_ms, event_type AS modality
        FROM events"""),
    ("thin", "SELECT * FROM trace QUALIFY row_number() OVER (PARTITION BY session_id, t_ms // 4320000 ORDER BY t_ms, sample_id) = 1"),
    ("sliced", "SELECT *, least(t_ms * 3 // 2592000000, 2) AS seg FROM thin WHERE t_ms <= 2592000000"),
    ("nb", """
        SELECT a.session_id, a.seg, a.sample_id AS i, b.sample_id AS j, (a.x - b.x) * (a.x - b.x) + (a.y - b.y) * (a.y - b.y) AS d2, abs(a.t_ms - b.t_ms) AS dt
        FROM sliced a JOIN sliced b ON a.session_id = b.session_id AND a.seg = b.seg WHERE (a.x - b.x) * (a.x - b.x) + (a.y - b.y) * (a.y - b.y) <= 400"""),
    ("core", "SELECT session_id, seg, i FROM nb GROUP BY ALL HAVING count(*) >= 5"),
    ("link", "SELECT n.i, n.j FROM nb n JOIN core a ON a.i = n.i JOIN core b ON b.i = n.j"),
    ("reach", "SELECT i, i AS lab FROM core UNION SELECT l.j, r.lab FROM reach r JOIN link l ON l.i = r.i"),
    ("comp", "SELECT i, min(lab) AS cluster_id FROM reach GROUP BY i"),
    ("border", "SELECT n.i, arg_min(c.cluster_id, (n.d2, n.j)) AS cluster_id FROM nb n JOIN comp c ON c.i = n.j WHERE n.i NOT IN (SELECT i FROM core) GROUP BY n.i"),
    ("clus", """
        SELECT s.session_id, s.seg, s.sample_id, s.x, s.y, s.t_ms, coalesce(c.cluster_id, b.cluster_id) AS cluster_id,
          CASE WHEN c.i IS NOT NULL THEN 'core' WHEN b.i IS NOT NULL THEN 'border' ELSE 'noise' END AS role
        FROM sliced s LEFT JOIN comp c ON c.i = s.sample_id LEFT JOIN border b ON b.i = s.sample_id"""),
    ("hp", "SELECT DISTINCT session_id, seg, cluster_id, x, y FROM clus WHERE cluster_id IS NOT NULL"),
    ("he", f"""
        SELECT a.session_id, a.seg, a.cluster_id, a.x AS ax, a.y AS ay, b.x AS bx, b.y AS by_
        FROM hp a JOIN hp b ON a.cluster_id = b.cluster_id AND a.seg = b.seg AND (a.x <> b.x OR a.y <> b.y) JOIN hp r ON r.cluster_id = a.cluster_id AND r.seg = a.seg
        GROUP BY ALL
        HAVING bool_and({CROSS} > 0 OR ({CROSS} = 0 AND (b.x - a.x) * (r.x - a.x) + (b.y - a.y) * (r.y - a.y) BETWEEN 0 AND (b.x - a.x) * (b.x - a.x) + (b.y - a.y) * (b.y - a.y)))
          AND bool_or({CROSS} > 0)"""),
    ("outl", "SELECT session_id, seg, cluster_id, count(*) AS vertices, sum(ax * by_ - bx * ay) / 2 AS area FROM he GROUP BY ALL"),
    ("pairs", "SELECT o.session_id, o.seg AS seg1, o.cluster_id AS c1, p.seg AS seg2, p.cluster_id AS c2 FROM outl o JOIN outl p ON o.session_id = p.session_id AND o.seg < p.seg"),
    ("apart", """
        SELECT DISTINCT seg1, c1, seg2, c2 FROM (
          SELECT q.seg1, q.c1, q.seg2, q.c2, e.ax, e.ay, e.bx, e.by_, max((e.bx - e.ax) * (v.ay - e.ay) - (e.by_ - e.ay) * (v.ax - e.ax)) AS most
          FROM pairs q JOIN he e ON e.seg = q.seg1 AND e.cluster_id = q.c1 JOIN he v ON v.seg = q.seg2 AND v.cluster_id = q.c2 GROUP BY ALL
          UNION ALL
          SELECT q.seg1, q.c1, q.seg2, q.c2, e.ax, e.ay, e.bx, e.by_, max((e.bx - e.ax) * (v.ay - e.ay) - (e.by_ - e.ay) * (v.ax - e.ax)) AS most
          FROM pairs q JOIN he e ON e.seg = q.seg2 AND e.cluster_id = q.c2 JOIN he v ON v.seg = q.seg1 AND v.cluster_id = q.c1 GROUP BY ALL
        ) WHERE most <= 0"""),
    ("zone", "SELECT q.*, q.seg1 || '.' || q.c1 || '+' || q.seg2 || '.' || q.c2 AS zone_id FROM pairs q LEFT JOIN apart s ON s.c1 = q.c1 AND s.c2 = q.c2 AND s.seg1 = q.seg1 AND s.seg2 = q.seg2 WHERE s.c1 IS NULL"),
    ("corner", """
        SELECT z.session_id, z.zone_id, v.ax AS x, v.ay AS y FROM zone z JOIN he v ON v.seg = z.seg1 AND v.cluster_id = z.c1 JOIN he e ON e.seg = z.seg2 AND e.cluster_id = z.c2
          GROUP BY z.session_id, z.zone_id, v.ax, v.ay HAVING bool_and((e.bx - e.ax) * (v.ay - e.ay) - (e.by_ - e.ay) * (v.ax - e.ax) >= 0)
        UNION
        SELECT z.session_id, z.zone_id, v.ax, v.ay FROM zone z JOIN he v ON v.seg = z.seg2 AND v.cluster_id = z.c2 JOIN he e ON e.seg = z.seg1 AND e.cluster_id = z.c1
          GROUP BY z.session_id, z.zone_id, v.ax, v.ay HAVING bool_and((e.bx - e.ax) * (v.ay - e.ay) - (e.by_ - e.ay) * (v.ax - e.ax) >= 0)
        UNION
        SELECT session_id, zone_id, ax + (bx - ax) * k, ay + (by_ - ay) * k FROM (
          SELECT z.session_id, z.zone_id, e.ax, e.ay, e.bx, e.by_,
            ((f.ax - e.ax) * (f.by_ - f.ay) - (f.ay - e.ay) * (f.bx - f.ax)) / nullif((e.bx - e.ax) * (f.by_ - f.ay) - (e.by_ - e.ay) * (f.bx - f.ax), 0) AS k,
            ((f.ax - e.ax) * (e.by_ - e.ay) - (f.ay - e.ay) * (e.bx - e.ax)) / nullif((e.bx - e.ax) * (f.by_ - f.ay) - (e.by_ - e.ay) * (f.bx - f.ax), 0) AS m
          FROM zone z JOIN he e ON e.seg = z.seg1 AND e.cluster_id = z.c1 JOIN he f ON f.seg = z.seg2 AND f.cluster_id = z.c2
        ) WHERE k BETWEEN 0 AND 1 AND m BETWEEN 0 AND 1"""),
    ("turn", "SELECT *, atan2(y - avg(y) OVER w, x - avg(x) OVER w) AS angle FROM corner WINDOW w AS (PARTITION BY session_id, zone_id)"),
    ("zarea", """
        SELECT session_id, zone_id, sum(x * y2 - x2 * y) / 2 AS area FROM (
          SELECT session_id, zone_id, x, y, coalesce(lead(x) OVER w, first_value(x) OVER w) AS x2, coalesce(lead(y) OVER w, first_value(y) OVER w) AS y2 FROM turn WINDOW w AS (PARTITION BY session_id, zone_id ORDER BY angle ROWS BETWEEN UNBOUNDED PRECEDING AND UNBOUNDED FOLLOWING)
        ) GROUP BY ALL"""),
    ("rim", """
        SELECT session_id, zone_id, x, y, coalesce(lead(x) OVER w, first_value(x) OVER w) AS x2, coalesce(lead(y) OVER w, first_value(y) OVER w) AS y2 FROM (
          SELECT *, atan2(y - avg(y) OVER v, x - avg(x) OVER v) AS angle FROM (SELECT DISTINCT session_id, zone_id, round(x, 7) AS x, round(y, 7) AS y FROM corner) WINDOW v AS (PARTITION BY session_id, zone_id)
        ) WINDOW w AS (PARTITION BY session_id, zone_id ORDER BY angle ROWS BETWEEN UNBOUNDED PRECEDING AND UNBOUNDED FOLLOWING)"""),
    ("pkey", "SELECT p_partkey AS point_id, CAST(regexp_extract(p_brand, '([0-9]+)', 1) AS INT) - 1 AS c, ((p_partkey * 7919) % 1000) / 1000.0::DOUBLE AS u, ((p_partkey * 104729) % 997) / 997.0::DOUBLE AS v, * FROM part"),
    ("pp", f"""
        SELECT point_id, -500.0::DOUBLE + 200.0::DOUBLE * (c % 5) + 200.0::DOUBLE * u * u AS x, -350.0::DOUBLE + 140.0::DOUBLE * (c // 5) + 140.0::DOUBLE * v AS y,
          2.3522::DOUBLE + (-500.0::DOUBLE + 200.0::DOUBLE * (c % 5) + 200.0::DOUBLE * u * u) * 0.0001::DOUBLE / {SHRINK}::DOUBLE AS lon,
          48.8566::DOUBLE + (-350.0::DOUBLE + 140.0::DOUBLE * (c // 5) + 140.0::DOUBLE * v) * 0.0001::DOUBLE AS lat,
          p_type AS kind, CASE WHEN p_size <= 15 THEN '1' WHEN p_size <= 30 THEN '2' ELSE '+2' END AS beds, CAST(1 + p_partkey % 5 AS VARCHAR) AS rating, p_retailprice AS price,
          CASE WHEN p_retailprice >= 975 THEN 'rest' WHEN p_retailprice >= 950 THEN '<975' WHEN p_retailprice >= 925 THEN '<950' ELSE '<925' END AS price_bin, p_name AS name, p_brand AS brand
        FROM pkey"""),
    ("ckey", "SELECT c_custkey AS point_id, c_nationkey AS c, ((c_custkey * 7919) % 1000) / 1000.0::DOUBLE AS u, ((c_custkey * 104729) % 997) / 997.0::DOUBLE AS v, c_mktsegment AS segment, n_name AS nation, r_name AS region, c_acctbal AS balance FROM customer JOIN nation ON c_nationkey = n_nationkey JOIN region ON n_regionkey = r_regionkey"),
    ("cp", f"SELECT point_id, -500.0::DOUBLE + 200.0::DOUBLE * (c % 5) + 200.0::DOUBLE * u * u AS x, -350.0::DOUBLE + 140.0::DOUBLE * (c // 5) + 140.0::DOUBLE * v AS y, 2.3522::DOUBLE + (-500.0::DOUBLE + 200.0::DOUBLE * (c % 5) + 200.0::DOUBLE * u * u) * 0.0001::DOUBLE / {SHRINK}::DOUBLE AS lon, 48.8566::DOUBLE + (-350.0::DOUBLE + 140.0::DOUBLE * (c // 5) + 140.0::DOUBLE * v) * 0.0001::DOUBLE AS lat, segment, nation, region, balance FROM ckey"),
    ("skey", "SELECT s_suppkey AS point_id, s_nationkey AS c, ((s_suppkey * 7919) % 1000) / 1000.0::DOUBLE AS u, ((s_suppkey * 104729) % 997) / 997.0::DOUBLE AS v, r_name AS region, s_acctbal AS balance FROM supplier JOIN nation ON s_nationkey = n_nationkey JOIN region ON n_regionkey = r_regionkey"),
    ("sp", f"SELECT point_id, 2.3522::DOUBLE + (-500.0::DOUBLE + 200.0::DOUBLE * (c % 5) + 200.0::DOUBLE * u * u) * 0.0001::DOUBLE / {SHRINK}::DOUBLE AS lon, 48.8566::DOUBLE + (-350.0::DOUBLE + 140.0::DOUBLE * (c // 5) + 140.0::DOUBLE * v) * 0.0001::DOUBLE AS lat, region, CASE WHEN balance >= 7500 THEN 'rest' WHEN balance >= 5000 THEN '<7500' WHEN balance >= 2500 THEN '<5000' WHEN balance >= 0 THEN '<2500' ELSE '<0' END AS bal FROM skey"),
    ("inh", "SELECT e.session_id, e.seg, e.cluster_id, p.point_id FROM pp p JOIN he e ON true GROUP BY ALL HAVING bool_and((e.bx - e.ax) * (p_y(p) - e.ay) - (e.by_ - e.ay) * (p_x(p) - e.ax) > 0)"),
    ("inc", ""),
    ("found", "SELECT a.session_id, a.seg || '.' || a.cluster_id || '+' || b.seg || '.' || b.cluster_id AS zone_id, a.point_id FROM inh a JOIN inh b ON a.session_id = b.session_id AND a.point_id = b.point_id AND a.seg < b.seg"),
    ("seen", "SELECT DISTINCT session_id, point_id FROM found"),
    ("foundc", "SELECT DISTINCT a.session_id, a.point_id FROM inc a JOIN inc b ON a.session_id = b.session_id AND a.point_id = b.point_id AND a.seg < b.seg"),
    ("facet", "SELECT point_id, 'kind' AS attr, kind AS val FROM pp UNION ALL SELECT point_id, 'beds', beds FROM pp UNION ALL SELECT point_id, 'rating', rating FROM pp UNION ALL SELECT point_id, 'price', price_bin FROM pp"),
    ("domain", "SELECT DISTINCT attr, val FROM facet UNION SELECT 'price', unnest(['<925', '<950', '<975', 'rest'])"),
    ("inc1", "SELECT s.session_id, f.attr, f.val, CAST(count(*) AS DOUBLE) AS add FROM seen s JOIN facet f ON s.point_id = f.point_id GROUP BY ALL"),
    ("fb", "SELECT session_id, attr, val, add AS raw, add / sum(add) OVER (PARTITION BY session_id) AS weight FROM inc1"),
    ("sig", "SELECT kind, beds, rating, price_bin, 'kind=' || kind || '|beds=' || beds || '|rating=' || rating || '|price=' || price_bin AS sig, count(*) AS n, min(point_id) AS first FROM pp GROUP BY ALL"),
    ("sigf", "SELECT sig, 'kind' AS attr, kind AS val FROM sig UNION ALL SELECT sig, 'beds', beds FROM sig UNION ALL SELECT sig, 'rating', rating FROM sig UNION ALL SELECT sig, 'price', price_bin FROM sig"),
    ("slice", "SELECT session_id, attr, max(weight) AS top, sqrt(sum(weight * weight)) AS norm, count(*) AS touched FROM fb GROUP BY ALL"),
    ("simf", "SELECT s.session_id, f.sig, f.attr, coalesce(w.weight, 0) AS w, s.top, s.norm, s.touched FROM sigf f JOIN slice s ON s.attr = f.attr LEFT JOIN fb w ON w.session_id = s.session_id AND w.attr = f.attr AND w.val = f.val"),
    ("psim", "SELECT session_id, 'kind=' || p.kind || '|beds=' || p.beds || '|rating=' || p.rating || '|price=' || p.price_bin AS sig, p.point_id, p.lat, p.lon FROM pp p, (SELECT DISTINCT session_id FROM trace)"),
    ("scored", "SELECT session_id, sig, round(avg(w / top), 12) AS sim FROM simf GROUP BY ALL"),
    ("anch", "SELECT session_id, point_id AS anchor, sim AS sim_f FROM (SELECT p.session_id, p.point_id, coalesce(s.sim, 0.0) AS sim FROM psim p LEFT JOIN scored s ON p.session_id = s.session_id AND p.sig = s.sig ANTI JOIN seen z ON z.session_id = p.session_id AND z.point_id = p.point_id) QUALIFY row_number() OVER (PARTITION BY session_id ORDER BY sim DESC, point_id) = 1"),
    ("pref", """
        SELECT q.session_id, p.point_id, p.lat, p.lon,
          round(((p.kind = a.kind)::INT + (p.beds = a.beds)::INT + (p.rating = a.rating)::INT + (p.price_bin = a.price_bin)::INT) / 4.0::DOUBLE, 12) AS sim
        FROM anch q JOIN pp a ON a.point_id = q.anchor JOIN pp p ON p.point_id <> q.anchor ANTI JOIN seen z ON z.session_id = q.session_id AND z.point_id = p.point_id"""),
    ("pl", "SELECT *, row_number() OVER (PARTITION BY session_id ORDER BY sim DESC, point_id) AS rank FROM pref"),
]


SPOT = "greatest(0, least(1023, CAST(floor(({} + 512) * 1024 / 1024) AS BIGINT)))"


def leaves(capacity: int, first: int | None = None) -> str:
    """Leaves of the quadtree over (-512, 512) with their boxes: depth, ix, iy, n, bx0, by0, bx1, by1."""
    some = "pp" if first is None else f"(SELECT * FROM pp WHERE point_id < {first})"
    level = f"SELECT depth, ix, iy, count(*) AS n FROM (SELECT k AS depth, {SPOT.format('x')} >> (10 - k) AS ix, {SPOT.format('y')} >> (10 - k) AS iy FROM {some}, range(0, 11) g(k)) GROUP BY ALL"
    return f"""SELECT depth, ix, iy, n, -512 + ix * side AS bx0, -512 + iy * side AS by0, -512 + (ix + 1) * side AS bx1, -512 + (iy + 1) * side AS by1 FROM (
      SELECT a.*, 1024.0::DOUBLE / (1 << a.depth) AS side FROM ({level}) a LEFT JOIN ({level}) b ON b.depth = a.depth - 1 AND b.ix = a.ix >> 1 AND b.iy = a.iy >> 1
      WHERE (a.n <= {capacity} OR a.depth = 10) AND (b.n IS NULL OR b.n > {capacity}))"""


def hits(leaf: str) -> str:
    """(session_id, zone_id, depth, ix, iy, n, full) of leaves that meet a zone: no edge of the zone has all four corners outside."""
    side = "(r.x2 - r.x) * ({} - r.y) - (r.y2 - r.y) * ({} - r.x)"
    sides = ", ".join(side.format(f"c.{y}", f"c.{x}") for x in ("bx0", "bx1") for y in ("by0", "by1"))
    return f"""SELECT r.session_id, r.zone_id, c.depth, c.ix, c.iy, c.n, bool_and(least({sides}) > 1e-9) AS inner_ FROM rim r JOIN ({leaf}) c ON true
      JOIN (SELECT session_id, zone_id, min(x) AS zx0, max(x) AS zx1, min(y) AS zy0, max(y) AS zy1 FROM rim GROUP BY ALL) z ON z.session_id = r.session_id AND z.zone_id = r.zone_id
      WHERE c.bx0 <= zx1 AND zx0 <= c.bx1 AND c.by0 <= zy1 AND zy0 <= c.by1 GROUP BY ALL HAVING bool_and(greatest({sides}) >= -1e-9)"""


def _fix(name: str, body: str) -> str:
    if name == "inc":
        body = dict(CHAIN)["inh"].replace("pp p", "cp p")
    return body.replace("p_x(p)", "p.x").replace("p_y(p)", "p.y")


def chain(select: str, **instead: str) -> str:
    """The chain before a statement; ``instead`` replaces bodies by name."""
    return "WITH RECURSIVE " + ",\n".join(f"{n}{'(i, lab)' if n == 'reach' else ''} AS ({_fix(n, instead.get(n, b))})" for n, b in CHAIN) + "\n" + select


def mined(g: int = 3, eps: float = 20, min_pts: int = 5) -> dict[str, str]:
    """Bodies for other parameters of the mining."""
    bodies = dict(CHAIN)
    return {
        "sliced": bodies["sliced"].replace("t_ms * 3 // 2592000000, 2", f"t_ms * {g} // 2592000000, {g - 1}"),
        "nb": bodies["nb"].replace("<= 400", f"<= {eps * eps}"),
        "core": bodies["core"].replace(">= 5", f">= {min_pts}"),
    }


def dist(a: str, b: str) -> str:
    return f"2 * 6371.0::DOUBLE * asin(least(1.0::DOUBLE, sqrt(pow(sin(radians({b}.lat - {a}.lat) / 2), 2) + cos(radians({a}.lat)) * cos(radians({b}.lat)) * pow(sin(radians({b}.lon - {a}.lon) / 2), 2))))"


GREEDY_TAIL = f""",
step(session_id, pos, chosen, swaps) AS (
  SELECT session_id, 5 AS pos, list({{'id': point_id, 'lat': lat, 'lon': lon}} ORDER BY rank) AS chosen, 0 AS swaps FROM pl WHERE rank <= 5 GROUP BY session_id
  UNION ALL
  SELECT session_id, pos + 1, CASE WHEN slot > 0 THEN list_concat(list_append(chosen[1:slot - 1], {{'id': pid, 'lat': plat, 'lon': plon}}), chosen[slot + 1:]) ELSE chosen END, swaps + CASE WHEN slot > 0 THEN 1 ELSE 0 END
  FROM (
    SELECT t.session_id, t.pos, t.chosen, t.swaps, c.point_id AS pid, c.lat AS plat, c.lon AS plon,
      coalesce(list_position(list_transform(range(1, len(t.chosen) + 1), lambda s:
        list_sum(list_transform(t.chosen, lambda m: {dist('m', 'c')})) - 2 * 6371.0::DOUBLE * asin(least(1.0::DOUBLE, sqrt(pow(sin(radians(c.lat - t.chosen[s].lat) / 2), 2) + cos(radians(t.chosen[s].lat)) * cos(radians(c.lat)) * pow(sin(radians(c.lon - t.chosen[s].lon) / 2), 2))))
        - list_sum(list_transform(t.chosen, lambda m: 2 * 6371.0::DOUBLE * asin(least(1.0::DOUBLE, sqrt(pow(sin(radians(t.chosen[s].lat - m.lat) / 2), 2) + cos(radians(m.lat)) * cos(radians(t.chosen[s].lat)) * pow(sin(radians(t.chosen[s].lon - m.lon) / 2), 2)))))) > 1e-9), true), 0) AS slot
    FROM step t JOIN pl c ON c.session_id = t.session_id AND c.rank = t.pos + 1 WHERE t.pos < 105
  )
),
ended AS (SELECT * FROM step QUALIFY row_number() OVER (PARTITION BY session_id ORDER BY pos DESC) = 1),
chosen_ AS (SELECT session_id, CAST(k AS INT) AS slot, chosen[k + 1].id AS point_id, CAST(swaps AS INT) AS swaps FROM ended, LATERAL (SELECT unnest(range(0, len(chosen))) AS k))
"""


def greedy_sql(select: str = "SELECT session_id, slot, point_id, swaps FROM chosen_", **instead: str) -> str:
    """The search for k = 5 over 100 scans, then a statement over its choice (chosen_)."""
    return chain("", **instead).rstrip() + GREEDY_TAIL + select


GREEDY = greedy_sql()

#: Explicit feedback: every action adds its weight to the facets of the nearest point.
ACTIONS = """SELECT n.session_id, f.attr, f.val, sum(n.w) AS add FROM (
    SELECT t.session_id, t.sample_id, min(CASE t.modality WHEN 'click' THEN 1.0 WHEN 'view' THEN 0.5 ELSE 2.0 END)::DOUBLE AS w, arg_min(p.point_id, ((t.x - p.x) * (t.x - p.x) + (t.y - p.y) * (t.y - p.y), p.point_id)) AS point_id
    FROM trace t JOIN pp p ON true WHERE t.modality <> 'error' AND t.t_ms <= 2592000000 GROUP BY t.session_id, t.sample_id
  ) n JOIN facet f ON f.point_id = n.point_id GROUP BY ALL"""
EXPLICIT = {"seen": "SELECT NULL::BIGINT AS session_id, NULL::BIGINT AS point_id WHERE false", "inc1": ACTIONS}
BOTH = {"fb": f"SELECT session_id, attr, val, raw, raw / sum(raw) OVER (PARTITION BY session_id) AS weight FROM (SELECT session_id, attr, val, sum(add) AS raw FROM (SELECT session_id, attr, val, add / sum(add) OVER (PARTITION BY session_id) AS add FROM inc1 UNION ALL SELECT * FROM ({ACTIONS})) GROUP BY ALL)"}
RAW_TRACE = """
    SELECT user_id AS session_id, event_id AS sample_id, CAST(CAST(json_extract_string(props, '$.k') AS BIGINT) - 50 AS DOUBLE) AS x, 50.0 - least(value, 100.0::DOUBLE) AS y,
      epoch_us(ts) // 1000 - 1704067200000 AS t_ms, event_type AS modality FROM events"""
