"""Routes and transitions derived from the given tables, as one SQL text for Spark and DuckDB alike.

Only integer arithmetic on non-negative operands, so both engines give the same rows. ``FIXTURES.md`` describes the derivation.
"""

from __future__ import annotations

from pyspark.sql import DataFrame, SparkSession, Window
from pyspark.sql import functions as F

#: Lattice nodes start here: a route of up to so many rows, whole, stays at positive ones.
OFFSET = 512


def _div(dialect: str) -> str:
    return "div" if dialect == "spark" else "//"


def _lattice_x(gx: str, gy: str) -> str:
    return f"({gx}) * 1000 + (({gx}) * 7919 + ({gy}) * 104729) % 401 - 200"


def _lattice_y(gx: str, gy: str) -> str:
    return f"({gy}) * 1000 + (({gx}) * 15485863 + ({gy}) * 7907) % 401 - 200"


def side_sql() -> str:
    return "(SELECT CAST(ceil(sqrt(CAST(count(*) AS DOUBLE))) AS BIGINT) AS g FROM part)"


def route_points_sql(dialect: str) -> str:
    """``route_points(route_id, seq, stop_id, x_m, y_m)`` from lineitem: a staircase over the lattice for each supplier and line."""
    d = _div(dialect)
    return f"""
WITH numbered AS (
  SELECT CAST(l_suppkey * 10 + l_linenumber AS BIGINT) AS route_id, CAST(l_partkey AS BIGINT) AS partkey, CAST(l_quantity AS BIGINT) AS qty,
         CAST(row_number() OVER (PARTITION BY l_suppkey, l_linenumber ORDER BY l_orderkey, l_partkey, l_quantity, l_extendedprice) AS INT) AS seq
  FROM lineitem),
starts AS (SELECT route_id, {OFFSET} + partkey % g AS gx0, {OFFSET} + partkey {d} g AS gy0 FROM numbered CROSS JOIN {side_sql()} WHERE seq = 1),
steps AS (
  SELECT route_id, seq,
         CASE WHEN seq > 1 AND qty % 2 = 0 THEN CASE WHEN route_id % 2 = 0 THEN 1 ELSE -1 END ELSE 0 END AS dx,
         CASE WHEN seq > 1 AND qty % 2 = 1 THEN CASE WHEN (route_id {d} 2) % 2 = 0 THEN 1 ELSE -1 END ELSE 0 END AS dy
  FROM numbered),
walked AS (
  SELECT route_id, seq, CAST(sum(dx) OVER w AS BIGINT) AS sx, CAST(sum(dy) OVER w AS BIGINT) AS sy
  FROM steps WINDOW w AS (PARTITION BY route_id ORDER BY seq ROWS BETWEEN UNBOUNDED PRECEDING AND CURRENT ROW)),
nodes AS (SELECT w.route_id, w.seq, s.gx0 + w.sx AS gx, s.gy0 + w.sy AS gy FROM walked w JOIN starts s ON w.route_id = s.route_id)
SELECT route_id, seq, CAST(gx * 4096 + gy AS BIGINT) AS stop_id, CAST({_lattice_x("gx", "gy")} AS BIGINT) AS x_m, CAST({_lattice_y("gx", "gy")} AS BIGINT) AS y_m
FROM nodes"""


def transitions_sql(dialect: str) -> str:
    """``transitions`` from events: consecutive check-ins of a user."""
    d = _div(dialect)
    k = "CAST(get_json_object(props, '$.k') AS BIGINT)" if dialect == "spark" else "CAST(json_extract(props, '$.k') AS BIGINT)"
    return f"""
WITH placed AS (
  SELECT event_id, user_id, CAST(ts AS TIMESTAMP) AS ts,
         {(OFFSET - 4) * 1000} + (CAST(round(value * 100) AS BIGINT) * 37 + event_id * 7919) % ((g + 8) * 1000) AS x,
         {(OFFSET - 4) * 1000} + {k} * (((g + 8) * 1000) {d} 100) + (event_id * 104729) % (((g + 8) * 1000) {d} 100) AS y
  FROM events CROSS JOIN {side_sql()}),
paired AS (
  SELECT event_id, user_id, ts, x, y, lag(x) OVER w AS px, lag(y) OVER w AS py FROM placed WINDOW w AS (PARTITION BY user_id ORDER BY ts, event_id))
SELECT CAST(event_id AS BIGINT) AS transition_id, CAST(user_id AS BIGINT) AS user_id, CAST(px AS BIGINT) AS o_x, CAST(py AS BIGINT) AS o_y, CAST(x AS BIGINT) AS d_x, CAST(y AS BIGINT) AS d_y, ts
FROM paired WHERE px IS NOT NULL"""


def large_transitions_sql(dialect: str) -> str:
    """``transitions`` from lineitem: short trips, six times as many."""
    d = _div(dialect)
    return f"""
WITH numbered AS (
  SELECT CAST(row_number() OVER (ORDER BY l_orderkey, l_linenumber, l_partkey, l_suppkey, l_quantity, l_extendedprice) AS BIGINT) AS transition_id,
         CAST(l_orderkey AS BIGINT) AS ok, CAST(l_linenumber AS BIGINT) AS ln, CAST(l_suppkey AS BIGINT) AS sk, CAST(l_partkey AS BIGINT) AS pk, CAST(l_shipdate AS TIMESTAMP) AS ts
  FROM lineitem),
origins AS (
  SELECT *, ({OFFSET} + pk % g) * 1000 + (ok * 37 + ln * 101) % 1000 - 500 AS o_x, ({OFFSET} + pk {d} g) * 1000 + (ok * 53 + sk * 211) % 1000 - 500 AS o_y
  FROM numbered CROSS JOIN {side_sql()})
SELECT transition_id, ok AS user_id, CAST(o_x AS BIGINT) AS o_x, CAST(o_y AS BIGINT) AS o_y,
       CAST(o_x + (ok * 7919 + sk * 104729) % 8001 - 4000 AS BIGINT) AS d_x, CAST(o_y + (ok * 15485863 + ln * 7907) % 8001 - 4000 AS BIGINT) AS d_y, ts
FROM origins"""


def clustered_points_sql() -> str:
    """A second space from embeddings: even ids are route points, odd ones check-ins; the same text in both engines."""
    first = "CAST(round(CAST(embedding[{i}] AS DOUBLE) * 100000) AS BIGINT)"
    return f"SELECT CAST(vec_id AS BIGINT) AS vec_id, CAST(label AS BIGINT) AS label, {first.format(i='0')} AS x_m, {first.format(i='1')} AS y_m FROM embeddings"


def _table(spark: SparkSession, sf_dir: str, sql: str, *names: str) -> DataFrame:
    return spark.sql(_named(sql, names), **{n: spark.read.parquet(f"{sf_dir}/{n}.parquet") for n in names})


def _named(sql: str, names: tuple[str, ...]) -> str:
    for n in names:
        sql = sql.replace(f"FROM {n}", f"FROM {{{n}}}")
    return sql


def route_points(spark: SparkSession, sf_dir: str) -> DataFrame:
    """The rows of :func:`route_points_sql`, by one window over one shuffle of lineitem: its text takes three."""
    rows = spark.read.parquet(f"{sf_dir}/lineitem.parquet")
    line = rows.agg(F.min("l_linenumber"), F.max("l_linenumber")).first()
    if line[0] is not None and (line[0] < 0 or line[1] > 9):
        # Two pairs of supplier and line may then be one route.
        return _table(spark, sf_dir, route_points_sql("spark"), "lineitem", "part")
    route, qty = F.col("route_id"), F.col("qty")
    rows = rows.selectExpr("CAST(l_suppkey * 10 + l_linenumber AS BIGINT) AS route_id", "CAST(l_partkey AS BIGINT) AS partkey", "CAST(l_quantity AS BIGINT) AS qty", "l_orderkey", "l_quantity", "l_extendedprice")
    by = Window.partitionBy("route_id").orderBy("l_orderkey", "partkey", "l_quantity", "l_extendedprice")
    sofar = by.rowsBetween(Window.unboundedPreceding, Window.currentRow)
    rows = rows.filter("route_id IS NOT NULL").select("route_id", "partkey", "qty", F.row_number().over(by).alias("seq"), F.first("partkey").over(sofar).alias("start"), F.first("qty").over(sofar).alias("qty0"), *(F.sum(F.when(qty % 2 == odd, 1).otherwise(0)).over(sofar).alias(f"n{odd}") for odd in (0, 1)))
    # The first row of a route is where it starts, not a step.
    x, y = (F.col(f"n{odd}") - F.when(F.col("qty0") % 2 == odd, 1).otherwise(0) for odd in (0, 1))
    side = spark.sql(_named(side_sql(), ("part",))[1:-1], part=spark.read.parquet(f"{sf_dir}/part.parquet"))
    up, right = F.expr("(route_id div 2) % 2 = 0"), route % 2 == 0
    at = rows.crossJoin(F.broadcast(side)).withColumns({"gx": F.expr(f"{OFFSET} + start % g") + F.when(right, x).otherwise(-x), "gy": F.expr(f"{OFFSET} + start div g") + F.when(up, y).otherwise(-y)})
    return at.selectExpr("route_id", "seq", "CAST(gx * 4096 + gy AS BIGINT) AS stop_id", f"CAST({_lattice_x('gx', 'gy')} AS BIGINT) AS x_m", f"CAST({_lattice_y('gx', 'gy')} AS BIGINT) AS y_m")


def transitions(spark: SparkSession, sf_dir: str) -> DataFrame:
    return _table(spark, sf_dir, transitions_sql("spark"), "events", "part")


def large_transitions(spark: SparkSession, sf_dir: str) -> DataFrame:
    return _table(spark, sf_dir, large_transitions_sql("spark"), "lineitem", "part")


def clustered_points(spark: SparkSession, sf_dir: str) -> DataFrame:
    return _table(spark, sf_dir, clustered_points_sql(), "embeddings")
