r"""URL filters by rules and by trust propagated over the link graph, in DataFrame functions only.

Rules judge a url by host (itself and all subdomains) and path prefix; the longest rule wins.
Hosts with ruled pages are the seeds for all other pages: trust starts at hosts in proportion to
their allowed pages and flows along links (personalised PageRank), distrust starts at hosts in
proportion to their blocked pages and flows against the links, from the linked host to whoever
links to it. A page without a rule is blocked if its host has a larger share of all distrust than
of all trust.

All mass is counted in integers (PAGE parts for each ruled page, so that what arrives at a host does not
depend on how many pages are elsewhere), and what a host passes on is
cut down to whole parts for each edge, so results don't depend on the order of sums. Edges are
distinct pairs of hosts with the number of links as weight, from absolute links in the html.
What a dangling host would pass on is dropped, which lowers all its followers alike.

Defined results: a null url or one without "://" has an empty host and path, no rule and, as no
mass reaches an empty host, the verdict allow; pages without html have no links; repeated rows are
judged one by one and their links count again; an empty table gives an empty result; only the
named columns are read. Hosts and edges are aggregated before every shuffle; a hot host's
pages meet only in partial aggregates and in a join whose one side has a row per host, which the engine splits by
rows where one host has many (adaptive skew handling) or turns into a broadcast below its own limit.
"""

from __future__ import annotations

from dataclasses import dataclass

from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

from .graph import checkpointed

#: Share of mass passed on in percent, parts of a page's mass, steps between checkpoints.
DAMPING, PAGE, STEPS = 85, 10**12, 4


@dataclass(frozen=True)
class Rule:
    """One rule; text is written like ``net/de/``: the host, then the path's start."""

    text: str
    block: bool

    @property
    def host(self) -> str:
        return self.text.split("/", 1)[0]

    @property
    def path(self) -> str:
        return "/" + self.text.split("/", 1)[1] if "/" in self.text else ""


RULES = [Rule("com/en/", True), Rule("example.com/en/7", False), Rule("net/de/", False), Rule("example.net/de/8", True), Rule("org/es/", True)]

UPPER, LOWER = "ABCDEFGHIJKLMNOPQRSTUVWXYZ", "abcdefghijklmnopqrstuvwxyz"


def host_of(url: Column) -> Column:
    """After the first "://" up to "/", "?", "#" or the end, A-Z lower-cased; empty without "://"."""
    return F.translate(F.regexp_extract(F.coalesce(url, F.lit("")), r"(?s)^.*?://([^/?#]*)", 1), UPPER, LOWER)


def path_of(url: Column) -> Column:
    """What follows the host up to "?", "#" or the end."""
    return F.regexp_extract(F.coalesce(url, F.lit("")), r"(?s)^.*?://[^/?#]*([^?#]*)", 1)


def _fits(rule: Rule, host: Column, path: Column) -> Column:
    return ((host == rule.host) | host.endswith("." + rule.host)) & path.startswith(rule.path)


def with_rule(pages: DataFrame, rules: list[Rule] | None = None) -> DataFrame:
    """Adds ``rule`` (the text of the longest that fits, the earlier of equals) and ``blocked`` to rows with host and path."""
    rule, blocked = F.lit(None).cast("string"), F.lit(None).cast("boolean")
    for r in sorted(RULES if rules is None else rules, key=lambda r: len(r.text)):
        fits = _fits(r, F.col("host"), F.col("path"))
        rule, blocked = F.when(fits, F.lit(r.text)).otherwise(rule), F.when(fits, F.lit(r.block)).otherwise(blocked)
    return pages.withColumns({"rule": rule, "blocked": blocked})


def host_edges(pages: DataFrame, url: Column, html: Column) -> DataFrame:
    """(src, dst, n): links between different hosts."""
    # a lazy start, so that only the links' own beginnings are looked at
    links = F.regexp_extract_all(F.coalesce(html, F.lit("")), F.lit(r"""(?i)<a\b[^>]*?\bhref\s*=\s*["']?\s*([a-z][a-z0-9+.-]*://[^/?#"'\s>]*)"""), 1)
    found = pages.where(html.contains("://")).select(host_of(url).alias("src"), F.explode(links).alias("link"))
    return found.select("src", host_of(F.col("link")).alias("dst")).where("src <> '' AND dst <> '' AND src <> dst").groupBy("src", "dst").agg(F.count("*").alias("n"))


def _parts(x: str, by: str) -> str:
    """The whole quotient, which div would squeeze into 64 bits."""
    return f"CAST(({x} - {x} % {by}) / {by} AS DECIMAL(38,0))"


def propagate(seeds: DataFrame, edges: DataFrame) -> DataFrame:
    """(host, mass) of personalised PageRank from (host, mass) along (src, dst, n).

    ``fresh`` is what came in the last step and is still to be passed on. Each step passes on less than it
    got, in whole parts, so it runs out; steps after that change nothing.
    """
    out = edges.groupBy("src").agg(F.sum("n").alias("out"))
    weighted = checkpointed(edges.join(out, "src"))
    own = seeds.select("host", F.expr(_parts(f"(CAST(mass AS DECIMAL(38,0)) * {100 - DAMPING})", "100")).alias("mass"))
    # no join where there is nothing to pass along
    if weighted.isEmpty():
        return own
    state = own.withColumn("fresh", F.col("mass"))
    while True:
        for _ in range(STEPS):
            passed = state.where("fresh > 0").select(F.col("host").alias("src"), "fresh").join(weighted, "src").select(F.col("dst").alias("host"), F.expr(_parts(f"CAST(fresh * {DAMPING} * n AS DECIMAL(38,0))", "(100 * out)")).alias("fresh"))
            both = state.select("host", "mass", F.lit(0).cast("decimal(38,0)").alias("fresh")).unionByName(passed.select("host", F.col("fresh").alias("mass"), "fresh"))
            state = both.groupBy("host").agg(*(F.sum(c).cast("decimal(38,0)").alias(c) for c in ("mass", "fresh")))
        state = checkpointed(state)
        if state.where("fresh > 0").isEmpty():
            return state.select("host", "mass")


def judge(pages: DataFrame, id_col: str = "page_id", url_col: str = "url", html_col: str = "html", rules: list[Rule] | None = None) -> DataFrame:
    """One row per row of ``pages``: the id, ``host``, ``path``, ``rule`` and ``verdict``, with the host's ``trust`` and ``distrust`` in parts of a page's."""
    url, html = F.col(f"`{url_col}`").cast("string"), F.col(f"`{html_col}`").cast("string")
    ruled = with_rule(pages.select(F.col(f"`{id_col}`").alias("id"), host_of(url).alias("host"), path_of(url).alias("path")), rules)
    seeds = checkpointed(ruled.where("blocked IS NOT NULL AND host <> ''").groupBy("host").agg(F.count_if(~F.col("blocked")).alias("good"), F.count_if("blocked").alias("bad")))
    total = F.broadcast(seeds.agg(F.greatest(F.sum("good"), F.lit(1)).alias("all_good"), F.greatest(F.sum("bad"), F.lit(1)).alias("all_bad")))
    mass = lambda own: seeds.where(F.col(own) > 0).select("host", (F.col(own).cast("decimal(38,0)") * PAGE).cast("decimal(38,0)").alias("mass"))
    edges = checkpointed(host_edges(pages, url, html))
    trust = propagate(mass("good"), edges).withColumnRenamed("mass", "trust")
    distrust = propagate(mass("bad"), edges.select(F.col("dst").alias("src"), F.col("src").alias("dst"), "n")).withColumnRenamed("mass", "distrust")
    given = lambda c: F.coalesce(c, F.lit(0)).cast("decimal(38,0)").alias(c)
    by_graph = F.expr("CAST(distrust * all_good AS DECIMAL(38,0)) > CAST(trust * all_bad AS DECIMAL(38,0))").alias("by_graph")
    scores = trust.join(distrust, "host", "full").select("host", given("trust"), given("distrust")).crossJoin(total).select("host", "trust", "distrust", by_graph)
    found = ruled.join(scores, "host", "left").withColumns({c: given(c) for c in ("trust", "distrust")})
    verdict = F.when(F.coalesce("blocked", "by_graph"), "block").otherwise("allow")
    return found.select(F.col("id").alias(id_col), "host", "path", "rule", verdict.alias("verdict"), "trust", "distrust")
