"""URL filters: rules on hosts and paths, and for the rest a verdict on the host from the link graph.

Hosts with allowed pages are trusted seeds, hosts with blocked pages are distrusted ones, each in proportion to its pages. Trust runs
along links between hosts as a personalised PageRank from the trusted seeds; distrust runs against them from the blocked seeds, to
those who link there. A host is blocked if its distrust is more than ``ratio`` times its trust, each as a share of its seed pages.
Each seed page starts with the same fixed amount, however many others there are, so what it passes on does not fade as a table grows.
Ranks are whole numbers and shares are rounded down, so sums do not depend on their order and reruns agree; trust and distrust are
given in billionths, rounded down, the verdict is from the whole numbers.

Links are the absolute and protocol-relative targets of ``href`` and ``src`` attributes; a host's links to itself do not count.

Defined cases: a null url, or one without ``://``, has an empty host and path and fits no rule; the empty host has no links and is
allowed; a null html has no links; repeated rows stay and count each time; an empty table gives an empty table; other columns are
ignored.
"""

from __future__ import annotations

import string
from collections.abc import Sequence

from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

from .common import join_hosts, written

#: Whole of the trust and distrust that are given, and the amount of a seed page: products of 38 digits leave room for 1e11 pages and links.
UNIT, PAGE = 1_000_000_000, 10**15
STEPS, DAMPING = 10, 85
LINK = r"""(?i)(?:href|src)\s*=\s*["']?(?:[a-z][a-z0-9+.-]*:)?//([^/?#"'>\s]+)"""
#: Rules of the query, (verdict, host/path); a parameter of the operator.
RULES = (("allow", "org/"), ("block", "example.org/es/"), ("block", "example.org/en/1"), ("allow", "com/fr/"), ("block", "com/de/"))


def lower_ascii(x: Column) -> Column:
    return F.translate(x, string.ascii_uppercase, string.ascii_lowercase)


def with_host_and_path(pages: DataFrame, url: str = "url") -> DataFrame:
    """``pages`` with ``host`` (A-Z lower-cased) and ``path``, both empty for what is no url."""
    u = F.col(url).cast("string")
    at = F.length(F.substring_index(u, "://", 1)) + 4
    is_url = F.contains(u, F.lit("://"))
    host = F.regexp_extract(F.substring(u, at, F.length(u)), r"^[^/?#]*", 0)
    path = F.regexp_extract(F.substring(u, at + F.length(host), F.length(u)), r"^[^?#]*", 0)
    host, path = (F.when(is_url, x).otherwise("") for x in (host, path))
    return pages.withColumns({"host": lower_ascii(host), "path": path})


def matching_rule(rules: Sequence[tuple[str, str]]) -> tuple[Column, Column]:
    """Rule and verdict of ``host`` and ``path``: the longest rule that fits, null without one. For lists of a few hundred."""
    rule, verdict = F.lit(None).cast("string"), F.lit(None).cast("string")
    for what, r in sorted(rules, key=lambda x: (len(x[1]), x[1])):
        host, path = r.split("/", 1)
        fits = ((F.col("host") == host) | F.endswith("host", F.lit("." + host))) & F.startswith("path", F.lit("/" + path))
        rule, verdict = F.when(fits, F.lit(r)).otherwise(rule), F.when(fits, F.lit(what)).otherwise(verdict)
    return rule, verdict


def host_links(pages: DataFrame) -> DataFrame:
    """``pages(host, html)`` to ``(src, dst, n)``, links between different hosts."""
    links = pages.select(F.col("host").alias("src"), F.explode(F.regexp_extract_all(F.coalesce(F.col("html").cast("string"), F.lit("")), F.lit(LINK), F.lit(1))).alias("dst"))
    links = links.withColumn("dst", lower_ascii(F.col("dst"))).filter("src <> '' AND dst <> '' AND src <> dst")
    return links.groupBy("src", "dst").agg(F.count("*").alias("n"))


def _whole(x: str) -> str:
    return f"CAST({x} AS DECIMAL(38, 0))"


def _floor_div(a: str, b: str) -> str:
    """The whole part of a quotient of whole numbers of up to 38 digits; ``div`` has 64 bits only."""
    return _whole(f"({a} - {a} % {b}) / {b}")


def propagated(seeds: DataFrame, links: DataFrame, steps: int = STEPS, damping: int = DAMPING) -> DataFrame:
    """``(host, rank)`` after so many steps from ``seeds(host, n)`` along ``links(src, dst, n)``, both written tables; ranks are in units
    of which a seed page has ``PAGE``.

    A step gives each host ``damping`` percent of what its neighbours pass on, by number of links, and the rest to the seeds.
    """
    start = written(seeds.select("host", F.expr(_whole(f"{_whole('n')} * {PAGE}")).alias("rank")), "url-seeds")
    if start.isEmpty() or links.isEmpty():
        return start
    out = written(links.join(links.groupBy("src").agg(F.sum("n").alias("all")), "src"), "url-links")
    passed, kept, own = _floor_div(_whole("rank * n"), "`all`"), _floor_div(_whole(f"got * {damping}"), "100"), _floor_div(_whole(f"rank * {100 - damping}"), "100")
    now = start
    for _ in range(steps):
        moved = out.join(now.withColumnRenamed("host", "src"), "src").groupBy(F.col("dst").alias("host")).agg(F.sum(F.expr(passed)).alias("got"))
        both = moved.select("host", F.expr(kept).alias("rank")).unionByName(start.select("host", F.expr(own).alias("rank")))
        now = written(both.groupBy("host").agg(F.sum("rank").alias("rank")), "url-ranks")
    return now


def host_verdicts(seeds: DataFrame, links: DataFrame, ratio: int = 2, steps: int = STEPS, damping: int = DAMPING) -> DataFrame:
    """``(host, trust, distrust, blocked)`` from the written tables ``seeds(host, ruled, n)`` and ``links(src, dst, n)``; written."""
    back = links.select(F.col("dst").alias("src"), F.col("src").alias("dst"), "n")
    parts, none = [], F.expr(_whole("0"))
    for name, other, ruled, along in (("trust", "distrust", "allow", links), ("distrust", "trust", "block", back)):
        own = seeds.filter(F.col("ruled") == ruled).select("host", "n")
        parts.append(propagated(own, along, steps, damping).select("host", F.col("rank").alias(name), none.alias(other)))
    hosts = parts[0].unionByName(parts[1]).groupBy("host").agg(F.sum("trust").alias("trust"), F.sum("distrust").alias("distrust"))
    pages = {r.ruled: r.n for r in seeds.groupBy("ruled").agg(F.sum("n").alias("n")).collect()}
    good, bad = max(1, pages.get("allow", 0)), max(1, pages.get("block", 0))
    shares = {x: F.expr(_floor_div(_whole(f"{x} * {UNIT}"), _whole(str(PAGE * n)))).cast("long") for x, n in (("trust", good), ("distrust", bad))}
    blocked = F.expr(f"{_whole(f'distrust * {good}')} > {_whole(f'trust * {bad * ratio}')}")
    return written(hosts.select("host", *(x.alias(name) for name, x in shares.items()), blocked.alias("blocked")), "url-hosts")


def judge_urls(pages: DataFrame, rules: Sequence[tuple[str, str]] = RULES, ratio: int = 2, steps: int = STEPS, damping: int = DAMPING) -> DataFrame:
    """``(page_id, host, path, rule, verdict, trust, distrust)`` of each of ``pages(page_id, url, html)``."""
    rows = with_host_and_path(pages.select(F.col("page_id").cast("long").alias("page_id"), F.col("url").alias("url"), "html"))
    rule, ruled = matching_rule(rules)
    rows = rows.withColumns({"rule": rule, "ruled": ruled})
    links = written(host_links(rows), "url-host-links")
    rows = written(rows.select("page_id", "host", "path", "rule", "ruled"), "url-rules")
    seeds = written(rows.filter("ruled IS NOT NULL AND host <> ''").groupBy("host", "ruled").agg(F.count("*").alias("n")), "url-ruled")
    out = join_hosts(rows, host_verdicts(seeds, links, ratio, steps, damping), "host", "left")
    verdict = F.coalesce("ruled", F.when(F.col("blocked"), "block").otherwise("allow"))
    return out.select("page_id", "host", "path", "rule", verdict.alias("verdict"), F.coalesce("trust", F.lit(0)).alias("trust"), F.coalesce("distrust", F.lit(0)).alias("distrust"))
