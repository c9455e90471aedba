"""Verdicts of the link graph do not depend on how many other seeds there are."""

import pytest

from transitlens.llm.common import written
from transitlens.llm.url_filters import host_verdicts


@pytest.mark.parametrize("others", [10_000, 10_000_000, 3_000_000_000])
def test_a_seed_page_counts_beside_millions_of_others(spark, others):
    seeds = [("bad.net", "block", 1), ("far.net", "block", others), ("good.net", "allow", 1), ("near.net", "allow", others)]
    links = [(f"to{i}.net", "bad.net", 1) for i in range(200)] + [("good.net", f"from{i}.net", 1) for i in range(200)] + [(f"from{i}.net", "far2.net", 1) for i in range(200)]
    seeds = written(spark.createDataFrame(seeds, "host string, ruled string, n long"), "seeds")
    links = written(spark.createDataFrame(links, "src string, dst string, n long"), "links")
    got = {r.host: r.blocked for r in host_verdicts(seeds, links).collect()}
    assert all(got[f"to{i}.net"] for i in range(200)) and got["bad.net"] and got["far.net"]
    assert not any(got[f"from{i}.net"] for i in range(200)) and not got["good.net"]
