"""Bounded, authorized context for many anchors at once.

Order of work: the visible, live nodes of a scope first, so that nothing hidden can take a place in a
ranking or be named in a report, and links and anchors turned to the current versions of what they name;
then expansion over links whose ends are both visible, ranked in the complete order (severity, basis,
score, then keys) and cut by the limits; then containers and contents along the parent edges; then the
token budget. Whatever limits or budget left out is listed with its cause; nothing outside the visible
set ever is.
"""

from __future__ import annotations

from dataclasses import dataclass

from pyspark.sql import DataFrame, Window
from pyspark.sql import functions as F

from evigraph.operators.clearance import Caller


@dataclass(frozen=True)
class Limits:
    hops: int = 1
    per_node: int = 8
    total: int = 64
    tokens: int = 1 << 40
    up: int = 0
    down: int = 0
    hard_hops: int = 3
    hard_links: int = 512

    def checked(self) -> Limits:
        if self.hops > self.hard_hops or self.total > self.hard_links:
            raise ValueError("beyond the hard limits")
        return self


@dataclass
class ContextResponse:
    nodes: DataFrame  # anchor, node, hop, reason, relation, via, tokens
    truncated: DataFrame  # anchor, node, cause
    report: DataFrame  # anchor, n_nodes, n_policy, n_token, complete


def live(nodes: DataFrame) -> DataFrame:
    """What may be shown: withdrawn nodes go, and superseded ones, in whose place :func:`redirected` puts
    their current version."""
    return nodes.filter("current is not null and node = current")


def _full(links: DataFrame) -> DataFrame:
    """Links with all columns of the complete order."""
    for name, value in (("rank_basis", F.lit(0)), ("relation", F.lit(""))):
        links = links if name in links.columns else links.withColumn(name, value)
    return links


def redirected(links: DataFrame, nodes: DataFrame) -> DataFrame:
    """Links with the current versions of their ends in place of superseded ones; links of a withdrawn
    end go, as do those that come to join a node to itself, and those that become equal are one."""
    at = nodes.select("node", "current").filter("current is not null")
    j = links.join(at.select(F.col("node").alias("src"), F.col("current").alias("s")), "src").join(at.select(F.col("node").alias("dst"), F.col("current").alias("d")), "dst")
    best = [F.max(c).alias(c) for c in ("rank_severity", "rank_basis", "score")]
    return j.filter("s <> d").groupBy("scope", F.col("s").alias("src"), F.col("d").alias("dst"), "relation", "rule_id").agg(*best)


def in_scope(links: DataFrame, seen: DataFrame) -> DataFrame:
    """Links of one scope, both ends of which are in the visible set; others go whole."""
    v = seen.select("node", "scope")
    return links.join(v.withColumnRenamed("node", "src"), ["scope", "src"], "left_semi").join(v.withColumnRenamed("node", "dst"), ["scope", "dst"], "left_semi")


def _both(links: DataFrame) -> DataFrame:
    own = ("scope", "src", "dst", "rank_severity", "rank_basis", "score", "relation", "rule_id")
    one = links.select(*own, F.col("src").alias("node"), F.col("dst").alias("other"))
    return one.unionByName(links.select(*own, F.col("dst").alias("node"), F.col("src").alias("other")))


def expand(anchors: DataFrame, seen: DataFrame, links: DataFrame, limits: Limits) -> tuple[DataFrame, DataFrame]:
    """(reached: anchor, scope, node, hop, reason, relation, via), (cut: anchor, node, cause)."""
    limits = limits.checked()
    ends = _both(in_scope(_full(links), seen))
    none = F.lit(None).cast(dict(seen.dtypes)["node"])
    got = anchors.join(seen.select("node", "scope"), ["node", "scope"], "left_semi").select("anchor", "scope", "node", F.lit(0).alias("hop"), F.lit("anchor").alias("reason"), F.lit("").alias("relation"), none.alias("via")).distinct()
    front, cut = got, None
    order = [F.desc("rank_severity"), F.desc("rank_basis"), F.desc("score"), F.asc("src"), F.asc("dst"), F.asc("relation"), F.asc("rule_id")]
    for hop in range(1, limits.hops + 1):
        step = front.select("anchor", "scope", "node").join(ends, ["scope", "node"])
        step = step.withColumn("r", F.row_number().over(Window.partitionBy("anchor", "node").orderBy(*order)))
        step = step.withColumn("t", F.when(F.col("r") <= limits.per_node, F.row_number().over(Window.partitionBy("anchor", F.col("r") <= limits.per_node).orderBy(*order, F.asc("node")))))
        ok = F.coalesce(F.col("t") <= limits.total, F.lit(False))
        known = got.select("anchor", F.col("node").alias("other"))
        fresh = step.filter(ok).join(known, ["anchor", "other"], "left_anti").groupBy("anchor", "scope", F.col("other").alias("node")).agg(F.min(F.struct("rule_id", "relation", F.col("node").alias("via"))).alias("by"))
        front = fresh.select("anchor", "scope", "node", F.lit(hop).alias("hop"), F.concat(F.lit("link:"), F.col("by.rule_id")).alias("reason"), "by.relation", "by.via")
        over = step.filter(~ok).select("anchor", F.col("other").alias("node"), F.lit("links").alias("cause"))
        cut = over if cut is None else cut.unionByName(over)
        got = got.unionByName(front)
    beyond = front.select("anchor", "scope", "node").join(ends, ["scope", "node"]).select("anchor", F.col("other").alias("node"), F.lit("depth").alias("cause"))
    cut = beyond if cut is None else cut.unionByName(beyond)
    cut = cut.groupBy("anchor", "node").agg(F.max("cause").alias("cause")).join(got.select("anchor", "node"), ["anchor", "node"], "left_anti")
    return got, cut


def expand_spine(got: DataFrame, seen: DataFrame, spine: DataFrame, limits: Limits) -> tuple[DataFrame, DataFrame]:
    """Containers (up) and contents (down) of the anchors in ``got`` along parent edges (child, parent)
    whose ends are both visible, so that a hidden container hides what lies beyond it. Returns rows as
    :func:`expand` does: the new ones, and the next level as cut."""
    v = seen.select("node", "scope")
    edges = spine.join(v.select(F.col("node").alias("child"), "scope"), "child").join(v.select(F.col("node").alias("parent"), F.col("scope").alias("s2")), "parent").filter("scope = s2").select("child", "parent", "scope")
    new, cut = None, None
    for way, a, b, depth in (("up", "child", "parent", limits.up), ("down", "parent", "child", limits.down)):
        step = edges.select("scope", F.col(a).alias("via"), F.col(b).alias("node"))
        front = got.filter("hop = 0").select("anchor", "scope", F.col("node").alias("via"))
        for k in range(1, depth + 2 if depth else 1):
            level = front.join(step, ["scope", "via"]).groupBy("anchor", "scope", "node").agg(F.min("via").alias("via"))
            if k > depth:
                over = level.select("anchor", "node", F.lit("spine").alias("cause"))
                cut = over if cut is None else cut.unionByName(over)
                break
            rows = level.select("anchor", "scope", "node", F.lit(k).alias("hop"), F.lit(f"spine:{way}").alias("reason"), F.lit("").alias("relation"), "via")
            new = rows if new is None else new.unionByName(rows)
            front = level.select("anchor", "scope", F.col("node").alias("via"))
    if new is None:
        return got, got.select("anchor", "node", F.lit("spine").alias("cause")).filter("false")
    every = got.unionByName(new)
    least = Window.partitionBy("anchor", "node").orderBy("hop", "reason")
    every = every.withColumn("r", F.row_number().over(least)).filter("r = 1").drop("r")
    return every, cut.distinct().join(every.select("anchor", "node"), ["anchor", "node"], "left_anti")


def budget(reached: DataFrame, tokens: int, mode: str = "prefix") -> DataFrame:
    """``reached`` (anchor, ord, tokens) with ``fits``: up to the first that overflows, or with later
    smaller ones filled in."""
    if mode == "prefix":
        w = Window.partitionBy("anchor").orderBy("ord").rowsBetween(Window.unboundedPreceding, 0)
        return reached.withColumn("used", F.sum("tokens").over(w)).withColumn("fits", F.col("used") <= tokens)
    g = reached.groupBy("anchor").agg(F.sort_array(F.collect_list(F.struct("ord", "node", "tokens"))).alias("xs"))
    empty = F.struct(F.lit(0).cast("long").alias("used"), F.array().cast("array<long>").alias("took"))
    fold = F.aggregate("xs", empty, lambda s, x: F.when(s["used"] + x["tokens"] <= tokens, F.struct((s["used"] + x["tokens"]).cast("long").alias("used"), F.concat(s["took"], F.array(x["node"].cast("long"))).alias("took"))).otherwise(s))
    took = g.select("anchor", F.explode(fold["took"]).alias("node")).withColumn("took", F.lit(True))
    return reached.join(took, ["anchor", "node"], "left").withColumn("fits", F.coalesce("took", F.lit(False))).drop("took")


def retrieve_many(anchors: DataFrame, nodes: DataFrame, links: DataFrame, caller: Caller, limits: Limits = Limits(), mode: str = "prefix", spine: DataFrame | None = None) -> ContextResponse:  # noqa: B008
    """anchors (anchor, node, scope); nodes (node, scope, level, current, tokens); links (scope, src, dst,
    rank_severity, score, rule_id, and rank_basis and relation where known); spine (child, parent)."""
    allowed = nodes.filter(F.col("level") <= caller.level)
    seen = live(allowed)
    if links.isEmpty():
        links = links.filter("false")  # now the plan shows it too, and no node is dealt out to meet a link
    anchors = anchors.select("anchor", "node", "scope")
    now = anchors.join(allowed.select("node", "scope", "current"), ["node", "scope"]).select("anchor", F.col("current").alias("node"), "scope")
    reached, cut = expand(now, seen, redirected(_full(links), allowed), limits)
    if spine is not None:
        reached, more = expand_spine(reached, seen, spine, limits)
        cut = cut.join(reached.select("anchor", "node"), ["anchor", "node"], "left_anti").unionByName(more).groupBy("anchor", "node").agg(F.max("cause").alias("cause"))
    sized = reached.join(seen.select("node", "scope", "tokens"), ["scope", "node"])
    sized = sized.withColumn("ord", F.row_number().over(Window.partitionBy("anchor").orderBy("hop", "node")))
    split = budget(sized, limits.tokens, mode)
    kept = split.filter("fits").select("anchor", "node", "hop", "reason", "relation", "via", "tokens", "ord")
    late = split.filter("not fits").select("anchor", "node", F.lit("tokens").alias("cause"))
    truncated = cut.unionByName(late)
    n = kept.groupBy("anchor").agg(F.count("*").alias("n_nodes"), F.sum("tokens").alias("tokens_used"))
    c = truncated.groupBy("anchor").agg(F.sum(F.when(F.col("cause") != "tokens", 1).otherwise(0)).alias("n_policy"), F.sum(F.when(F.col("cause") == "tokens", 1).otherwise(0)).alias("n_token"))
    zero = F.lit(0).cast("long")
    report = anchors.select("anchor").distinct().join(n, "anchor", "left").join(c, "anchor", "left").select("anchor", *(F.coalesce(x, zero).cast("long").alias(x) for x in ("n_nodes", "tokens_used", "n_policy", "n_token")))
    report = report.withColumn("complete", (F.col("n_policy") == 0) & (F.col("n_token") == 0))
    return ContextResponse(kept, truncated, report)


def currency(anchors: DataFrame, state: DataFrame, stored: DataFrame, target: str) -> DataFrame:
    """(anchor, generation, run_id, caught_up, at_target): which projection an answer stands on, whether
    it covers all that is stored of the scope, and whether it is of the generation readers are pointed at."""
    s = state.select("scope", "generation", "run_id", F.col("watermark").alias("projected"))
    j = anchors.select("anchor", "scope").join(s, "scope", "left").join(stored.select("scope", F.col("watermark").alias("stored")), "scope", "left")
    return j.select("anchor", "generation", "run_id", F.col("projected").eqNullSafe(F.col("stored")).alias("caught_up"), F.coalesce(F.col("generation") == target, F.lit(False)).alias("at_target"))


def resolve(nodes: DataFrame, ids: DataFrame | None = None, since: int | None = None, until: int | None = None, kinds: tuple[str, ...] = ()) -> DataFrame:
    """(scope, node) of what a query names: by id (a table of node), by time [since, until), by kind."""
    out = nodes
    if since is not None:
        out = out.filter(F.col("us") >= since)
    if until is not None:
        out = out.filter(F.col("us") < until)
    if kinds:
        out = out.filter(F.col("kind").isin(*kinds))
    if ids is not None:
        out = out.join(ids.select("node").distinct(), "node", "left_semi")
    return out.select("scope", "node")


def render(nodes: DataFrame) -> DataFrame:
    """One text per anchor, in the order of selection."""
    g = nodes.groupBy("anchor").agg(F.sort_array(F.collect_list(F.struct("ord", "node", "hop", "reason"))).alias("xs"))
    return g.select("anchor", F.array_join(F.transform("xs", lambda x: F.format_string("%d@%d(%s)", x["node"], x["hop"], x["reason"])), ";").alias("text"))


def completeness(response: ContextResponse, anchors: DataFrame, nodes: DataFrame, links: DataFrame, caller: Caller, limits: Limits) -> DataFrame:
    """(anchor, expected, missing, violations): the exhaustive closure over links up to one step beyond the
    limit of hops, walked from the anchors without looking at what was returned, only not on through what was
    listed as left out by a limit; less what was returned or listed. And returned nodes that should not
    have been."""
    allowed = nodes.filter(F.col("level") <= caller.level)
    seen = live(allowed)
    ends = _both(in_scope(redirected(_full(links), allowed), seen)).select("scope", "node", "other").distinct()
    front = anchors.join(allowed.select("node", "scope", "current"), ["node", "scope"]).select("anchor", "scope", F.col("current").alias("node"))
    due = front = front.join(seen.select("node", "scope"), ["node", "scope"], "left_semi").select("anchor", "scope", "node").distinct()
    listed = response.truncated.select("anchor", "node").distinct()
    stopped = response.truncated.filter("cause = 'links'").select("anchor", "node").distinct()
    for _ in range(limits.hops + 1):
        on = front.join(stopped, ["anchor", "node"], "left_anti")
        front = on.join(ends, ["scope", "node"]).select("anchor", "scope", F.col("other").alias("node")).distinct()
        due = due.unionByName(front).distinct()
    told = response.nodes.select("anchor", "node").unionByName(listed).distinct()
    missing = due.join(told, ["anchor", "node"], "left_anti").groupBy("anchor").agg(F.count("*").alias("missing"))
    bad = response.nodes.join(seen.select("node"), "node", "left_anti").groupBy("anchor").agg(F.count("*").alias("violations"))
    zero = F.lit(0).cast("long")
    return due.groupBy("anchor").agg(F.count("*").alias("expected")).join(missing, "anchor", "left").join(bad, "anchor", "left").select("anchor", "expected", F.coalesce("missing", zero).alias("missing"), F.coalesce("violations", zero).alias("violations"))
