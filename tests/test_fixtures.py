"""Routes keep every row of the table they come from."""

import uuid

from transitlens.plans.shared import shared_dir
from transitlens.sources.fixtures import route_points


def test_routes_are_whole(spark):
    folder = f"{shared_dir(spark)}/fixtures-{uuid.uuid4().hex}"
    rows = [(o, 1, 1 + o % 2, o % 9, float(o % 50), 1.0) for o in range(230)]
    spark.createDataFrame(rows, "l_orderkey long, l_suppkey long, l_linenumber int, l_partkey long, l_quantity double, l_extendedprice double").write.parquet(f"{folder}/lineitem.parquet")
    spark.range(9).withColumnRenamed("id", "p_partkey").write.parquet(f"{folder}/part.parquet")
    got = route_points(spark, folder).collect()
    assert {(r.route_id, r.seq) for r in got} == {(route, i) for route in (11, 12) for i in range(1, 116)} and len(got) == 230
    assert all(r.x_m > 0 and r.y_m > 0 for r in got)
