"""Tables that the planning queries leave in the shared folder."""

from transitlens.plans import queries, shared


def test_planners_keep_what_their_plans_read_only(spark):
    since = shared.mark()
    _, _, points, *_, omega = queries._planner(spark, "/root/testdata/sf0.001")
    labels = {p.rsplit("/", 1)[-1].rsplit("-", 1)[0] for p in shared._PATHS[since:]}
    assert labels == {"route-heads", "stops", "planning", "edges", "omega"}
    assert points is None and omega.count() > 0
