"""DuckDB texts of the queries, written from the definitions and not from the plans."""

from __future__ import annotations

from ..sources.fixtures import large_transitions_sql, route_points_sql, transitions_sql

RP = f"rp AS ({route_points_sql('duckdb')})"
TR = f"tr AS ({transitions_sql('duckdb')})"
TR_LARGE = f"tr AS ({large_transitions_sql('duckdb')})"
TR_LATE = f"tr AS (SELECT * FROM ({transitions_sql('duckdb')}) WHERE ts >= TIMESTAMP '2024-01-10 00:00:00')"
EP = "ep AS (SELECT transition_id, 1 AS side, o_x AS x, o_y AS y FROM tr UNION ALL SELECT transition_id, 2, d_x, d_y FROM tr)"
ST = "st AS (SELECT stop_id, min(x_m) AS x, min(y_m) AS y FROM rp GROUP BY 1), through AS (SELECT DISTINCT stop_id, route_id FROM rp)"


def reverse(query: str, k: int, mode: str = "any", loose: bool = False, trips: str = TR) -> str:
    """Reverse result of the query points ``query(query_id, x, y, excluded)``: endpoints with fewer than k strictly nearer routes.

    An endpoint with k nearer routes among the stops of the cells around it is out at once; the rest count all stops.
    """
    need = k + loose
    keep = "" if mode == "any" else "HAVING bit_or(side) = 3"
    return f"""
WITH RECURSIVE {RP}, {trips}, {EP}, {ST}, q AS ({query}),
e AS (SELECT query_id, any_value(excluded) AS excluded, transition_id, side, any_value(ep.x) AS x, any_value(ep.y) AS y,
             min((ep.x - q.x) * (ep.x - q.x) + (ep.y - q.y) * (ep.y - q.y)) AS dq
      FROM ep CROSS JOIN q GROUP BY query_id, transition_id, side),
around AS (SELECT e.*, e.x // 2000 + i AS cx, e.y // 2000 + j AS cy FROM e, (SELECT unnest([-1, 0, 1]) AS i), (SELECT unnest([-1, 0, 1]) AS j)),
lost AS (
  SELECT query_id, transition_id, side FROM around a JOIN st s ON s.x // 2000 = a.cx AND s.y // 2000 = a.cy JOIN through t ON t.stop_id = s.stop_id
  WHERE (a.x - s.x) * (a.x - s.x) + (a.y - s.y) * (a.y - s.y) < a.dq AND (a.excluded IS NULL OR t.route_id <> a.excluded)
  GROUP BY 1, 2, 3 HAVING count(DISTINCT t.route_id) >= {need}),
rest AS (SELECT e.* FROM e ANTI JOIN lost l ON e.query_id = l.query_id AND e.transition_id = l.transition_id AND e.side = l.side),
more AS (
  SELECT r.query_id, r.transition_id, r.side, count(DISTINCT t.route_id) AS n FROM rest r JOIN st s ON (r.x - s.x) * (r.x - s.x) + (r.y - s.y) * (r.y - s.y) < r.dq
  JOIN through t ON t.stop_id = s.stop_id AND (r.excluded IS NULL OR t.route_id <> r.excluded) GROUP BY 1, 2, 3),
won AS (SELECT r.query_id, r.transition_id, r.side FROM rest r LEFT JOIN more m USING (query_id, transition_id, side) WHERE coalesce(m.n, 0) < {need})
SELECT query_id, transition_id, CAST(bit_or(side) AS INTEGER) AS mask FROM won GROUP BY 1, 2 {keep}"""


def whole_route(*routes: int) -> str:
    return f"SELECT route_id AS query_id, x_m AS x, y_m AS y, route_id AS excluded FROM rp WHERE route_id IN ({', '.join(map(str, routes))})"


#: Every endpoint with each route that fewer than 25 others are strictly nearer than, and how many: a radius that holds 25 routes is found
#: first among the stops of the cells around, then all stops within it are taken.
RANKED = f"""WITH {RP}, {TR}, {EP}, {ST},
n_all AS (SELECT least(25, count(DISTINCT route_id)) AS n FROM rp),
near AS (
  SELECT transition_id, side, route_id, min((e.x - s.x) * (e.x - s.x) + (e.y - s.y) * (e.y - s.y)) AS d
  FROM (SELECT *, x // 2000 + i AS cx, y // 2000 + j AS cy FROM ep, (SELECT unnest([-1, 0, 1]) AS i), (SELECT unnest([-1, 0, 1]) AS j)) e
  JOIN st s ON s.x // 2000 = cx AND s.y // 2000 = cy JOIN through USING (stop_id) GROUP BY 1, 2, 3),
bar AS (SELECT transition_id, side, list_sort(list(d))[(SELECT n FROM n_all)] AS d FROM near GROUP BY 1, 2),
reach AS (SELECT ep.*, coalesce(bar.d, 4000000000000000) AS bar FROM ep LEFT JOIN bar USING (transition_id, side)),
dist AS (
  SELECT r.transition_id, r.side, route_id, min((r.x - s.x) * (r.x - s.x) + (r.y - s.y) * (r.y - s.y)) AS d
  FROM reach r JOIN st s ON (r.x - s.x) * (r.x - s.x) + (r.y - s.y) * (r.y - s.y) <= r.bar JOIN through USING (stop_id) GROUP BY 1, 2, 3),
ranked AS (SELECT *, rank() OVER (PARTITION BY transition_id, side ORDER BY d) AS rank FROM dist)"""
#: For k = 1 a stop wins the endpoints it is nearest to, ties included.
NEAREST = """least AS (
  SELECT ep.transition_id, ep.side, ep.x, ep.y, min((ep.x - s.x) * (ep.x - s.x) + (ep.y - s.y) * (ep.y - s.y)) AS d FROM ep CROSS JOIN st s GROUP BY ALL),
near AS (SELECT l.transition_id, l.side, s.stop_id FROM least l JOIN st s ON (l.x - s.x) * (l.x - s.x) + (l.y - s.y) * (l.y - s.y) <= l.d)"""
SEGMENTS = "seg AS (SELECT route_id, seq, stop_id AS src, lead(stop_id) OVER w AS dst, CAST(round(sqrt(CAST((x_m - lead(x_m) OVER w) * (x_m - lead(x_m) OVER w) + (y_m - lead(y_m) OVER w) * (y_m - lead(y_m) OVER w) AS DOUBLE))) AS BIGINT) AS n FROM rp WINDOW w AS (PARTITION BY route_id ORDER BY seq))"
EDGES = "edges AS (SELECT src, dst, min(n) AS length_m FROM (SELECT src, dst, n FROM seg WHERE dst IS NOT NULL UNION ALL SELECT dst, src, n FROM seg WHERE dst IS NOT NULL) WHERE src <> dst GROUP BY 1, 2)"


def vertex_omega() -> str:
    return f"WITH {RP}, {TR}, {EP}, {ST}, {NEAREST} SELECT CAST(1 AS INTEGER) AS k, stop_id, transition_id, CAST(bit_or(side) AS INTEGER) AS mask FROM near GROUP BY stop_id, transition_id"


def _stop_masks() -> str:
    """``won(k, stop_id, transition_id, mask)`` from ``RANKED``: a stop no farther than the k-th nearest route wins the endpoint."""
    return """, bars AS (SELECT transition_id, side, k, max(d) AS bar FROM (SELECT transition_id, side, k, d FROM ranked, (SELECT unnest([1, 5, 10]) AS k) WHERE rank <= k) GROUP BY 1, 2, 3),
won AS (SELECT b.k, s.stop_id, ep.transition_id, bit_or(ep.side) AS mask FROM bars b JOIN ep ON ep.transition_id = b.transition_id AND ep.side = b.side
  JOIN st s ON s.x // 4000 BETWEEN (ep.x - CAST(ceil(sqrt(bar)) AS BIGINT)) // 4000 AND (ep.x + CAST(ceil(sqrt(bar)) AS BIGINT)) // 4000
   AND (ep.x - s.x) * (ep.x - s.x) + (ep.y - s.y) * (ep.y - s.y) <= bar GROUP BY 1, 2, 3)"""


def vertex_counts(ks: tuple[int, ...]) -> str:
    return RANKED + _stop_masks() + f" SELECT CAST(k AS INTEGER) AS k, stop_id, count(*) AS n_any, CAST(count_if(mask = 3) AS BIGINT) AS n_both FROM won WHERE k IN ({', '.join(map(str, ks))}) GROUP BY 1, 2"


def _paths(stops: int, percent: int, only: str = "") -> str:
    """``done(query_id, path, len, id)``: all loopless paths within the limit, by recursion."""
    return f""", {SEGMENTS}, {EDGES},
pq AS (
  SELECT a.route_id AS query_id, a.stop_id AS src, b.stop_id AS dst, (SELECT sum(n) FROM seg WHERE seg.route_id = a.route_id AND seq < {stops}) * {percent} // 100 AS lim
  FROM rp a JOIN rp b ON a.route_id = b.route_id AND a.seq = 1 AND b.seq = {stops} {only}),
walk AS (
  SELECT query_id, src AS here, dst, CAST(lim AS BIGINT) AS lim, CAST(0 AS BIGINT) AS len, [src] AS path FROM pq
  UNION ALL
  SELECT w.query_id, e.dst, w.dst, w.lim, w.len + e.length_m, list_append(w.path, e.dst) FROM walk w JOIN edges e ON e.src = w.here
  JOIN st a ON a.stop_id = e.dst JOIN st b ON b.stop_id = w.dst
  WHERE w.here <> w.dst AND NOT list_contains(w.path, e.dst) AND w.len + e.length_m + sqrt(CAST((a.x - b.x) * (a.x - b.x) + (a.y - b.y) * (a.y - b.y) AS DOUBLE)) * 0.99 - 16 <= w.lim),
done AS (SELECT query_id, path, len, row_number() OVER (ORDER BY query_id, len, path) AS id FROM walk WHERE here = dst AND len <= lim),
masks AS (SELECT id, transition_id, bit_or(mask) AS m FROM (SELECT id, unnest(path) AS stop_id FROM done) JOIN won USING (stop_id) WHERE k = 10 GROUP BY 1, 2)"""


def _ranked_paths(objective: str, mode: str) -> str:
    value = "count(*)" if mode == "any" else "count_if(m = 3)"
    order = {"max": "coalesce(v, 0) DESC, ", "min": "coalesce(v, 0), ", "shortest": ""}[objective]
    return f"""SELECT d.*, coalesce(v, 0) AS v, row_number() OVER (PARTITION BY query_id ORDER BY {order}len, path) AS r FROM done d LEFT JOIN (SELECT id, {value} AS v FROM masks GROUP BY 1) USING (id)"""


def _recursive(text: str) -> str:
    return text.replace("WITH ", "WITH RECURSIVE ", 1)


def plan(objective: str, mode: str, stops: int, percent: int) -> str:
    """The best of all paths by value, length and path; each one's won transitions united."""
    return _recursive(RANKED + _stop_masks() + _paths(stops, percent)) + f"""
SELECT query_id, array_to_string(path, '-') AS path, CAST(len AS BIGINT) AS length_m, CAST(v AS BIGINT) AS n_transitions, CAST(len(path) AS BIGINT) AS n_stops FROM ({_ranked_paths(objective, mode)}) WHERE r = 1"""


def replanned(stops: int) -> str:
    return _recursive(RANKED + _stop_masks() + _paths(stops, 100)) + f""",
old AS (SELECT route_id AS query_id, count(DISTINCT transition_id) AS old FROM rp JOIN won USING (stop_id) WHERE k = 10 AND seq <= {stops} GROUP BY 1)
SELECT b.query_id, CAST(lim AS BIGINT) AS max_len_m, CAST(len AS BIGINT) AS length_m, coalesce(old, 0) AS old, CAST(v AS BIGINT) AS new
FROM ({_ranked_paths('max', 'any')}) b JOIN pq USING (query_id) LEFT JOIN old USING (query_id) WHERE r = 1"""


def four_routes(route: int, stops: int, percent: int) -> str:
    kinds = " UNION ALL ".join(f"SELECT '{kind}' AS kind, CAST(len AS BIGINT) AS length_m, CAST(v AS BIGINT) AS n_transitions, CAST(len(path) AS BIGINT) AS n_stops FROM ({_ranked_paths(kind, 'any')}) WHERE r = 1" for kind in ("shortest", "max", "min"))
    return _recursive(RANKED + _stop_masks() + _paths(stops, percent, f"WHERE a.route_id = {route}")) + f"""
SELECT 'original' AS kind, (SELECT CAST(sum(n) AS BIGINT) FROM seg WHERE route_id = {route} AND seq < {stops}) AS length_m,
       (SELECT count(DISTINCT transition_id) FROM rp JOIN won USING (stop_id) WHERE k = 10 AND route_id = {route} AND seq <= {stops}) AS n_transitions, CAST({stops} AS BIGINT) AS n_stops
UNION ALL {kinds}"""


def shortest(targets: str, cap: int) -> str:
    return f"""
WITH RECURSIVE {RP}, {SEGMENTS}, {EDGES}, t AS ({targets}),
w AS (SELECT target, target AS src, CAST(0 AS BIGINT) AS d FROM t UNION SELECT w.target, e.src, w.d + e.length_m FROM w JOIN edges e ON e.dst = w.src WHERE w.d + e.length_m <= {cap})
SELECT target, src, CAST(min(d) AS BIGINT) AS length_m FROM w GROUP BY 1, 2"""


def cell(x: str, y: str, level: int) -> str:
    return f"((((CAST({x} AS BIGINT) + 1073741824) >> {level}) << 31) | ((CAST({y} AS BIGINT) + 1073741824) >> {level}))"


BOARD = """nearby AS (
  SELECT t.transition_id, t.ts, s.stop_id, (t.o_x - s.x) * (t.o_x - s.x) + (t.o_y - s.y) * (t.o_y - s.y) AS d
  FROM tr t JOIN st s ON s.x BETWEEN t.o_x - 2000 AND t.o_x + 2000 AND s.y BETWEEN t.o_y - 2000 AND t.o_y + 2000),
first_stop AS (SELECT transition_id, ts, arg_min(stop_id, {'d': d, 's': stop_id}) AS stop_id FROM nearby WHERE d <= 4000000 GROUP BY 1, 2),
board AS (SELECT transition_id, ts, route_id FROM first_stop JOIN through USING (stop_id))"""


def transitions_text(large: bool = False) -> str:
    return f"SELECT transition_id, user_id, o_x, o_y, d_x, d_y, CAST(epoch_us(ts) AS BIGINT) AS ts_us FROM ({large_transitions_sql('duckdb') if large else transitions_sql('duckdb')})"
