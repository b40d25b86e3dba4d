"""Record status from corrections.

A correction is live if it stands in its target's scope and no live retraction names it. Live
retractions win; else the latest live, attested amendment supersedes; an unattested live amendment is
pending. Retractions of retractions and amendments of amendments are followed to any depth; corrections
that name each other in a cycle are an error.
"""

from __future__ import annotations

from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from evigraph.plans.store import written

#: Doublings of a pointer's reach after which a chain must have ended.
DOUBLINGS = 64


def valid_corrections(nodes: DataFrame) -> DataFrame:
    """(node, scope, us, target, kind, attested) of corrections whose target is stored in their scope."""
    target = nodes.select(F.col("node").alias("target"), F.col("scope").alias("target_scope"))
    return nodes.filter("target is not null").select("node", "scope", "us", "target", "kind", "attested").join(target, "target").filter("scope = target_scope").drop("target_scope")


def bad_targets(nodes: DataFrame) -> DataFrame:
    """(node, target, reason) of corrections of another scope or of nothing stored."""
    target = nodes.select(F.col("node").alias("target"), F.col("scope").alias("target_scope"))
    c = nodes.filter("target is not null").select("node", "scope", "target").join(target, "target", "left")
    return c.filter("target_scope is null or target_scope <> scope").select("node", "target", F.when(F.col("target_scope").isNull(), "missing").otherwise("cross_scope").alias("reason"))


def live(corrections: DataFrame) -> DataFrame:
    """The corrections that are not themselves withdrawn. The withdrawn retractions are found by turns: each
    set follows from the one before, lies inside or around it, and the true one follows from itself."""
    by = corrections.filter("kind = 'retraction'").select("node", "target").distinct()
    chained = written(by.join(by.select(F.col("node").alias("target")).distinct(), "target", "left_semi").select("node", "target"))
    gone, sizes = None, [-1, 0]
    while True:
        acting = chained if gone is None else chained.join(gone, "node", "left_anti")
        gone = written(acting.select(F.col("target").alias("node")).distinct())
        sizes.append(gone.count())
        if sizes[-1] == sizes[-2]:
            break
        if sizes[-1] == sizes[-3]:
            raise ValueError("retractions withdraw each other in a cycle")
    return corrections.join(by.join(gone, "node", "left_anti").select(F.col("target").alias("node")).distinct(), "node", "left_anti")


def winner(amendments: DataFrame) -> DataFrame:
    """(target, current): the amendment recorded last, ties to the higher id."""
    return amendments.groupBy("target").agg(F.max_by("node", F.struct("us", "node")).alias("current"), F.count("*").alias("n"))


def resolve(nodes: DataFrame, require_attestation: bool = True, as_of: int | None = None) -> DataFrame:
    """node, status, current of every node (node, scope, us, kind, target, attested)."""
    if as_of is not None:
        nodes = nodes.filter(F.col("us") <= as_of)
    c = live(valid_corrections(nodes))
    gone = c.filter("kind = 'retraction'").groupBy(F.col("target").alias("node")).agg(F.max_by("node", F.struct("us", "node")).alias("gone_by"))
    amendments = c.filter("kind = 'amendment'")
    counted = amendments.filter("attested") if require_attestation else amendments
    best = winner(counted).select(F.col("target").alias("node"), F.col("current").alias("over_by"))
    s = nodes.select("node", "scope", "kind", "attested", "target").join(gone, "node", "left").join(best, "node", "left")
    pending = (F.col("kind") == "amendment") & (~F.col("attested") if require_attestation else F.lit(False))
    status = F.when(F.col("gone_by").isNotNull(), "retracted").when(F.col("over_by").isNotNull(), "superseded").when(pending, "pending_amendment").otherwise("current")
    s = s.select("node", "scope", "kind", status.alias("status"), F.when(F.col("gone_by").isNotNull(), F.lit(None)).otherwise(F.coalesce("over_by", "node")).alias("current"))
    # an amendment of an amendment: follow the pointers, doubling their reach
    at = written(s.filter("current <> node").select("node", "current"))
    for _ in range(DOUBLINGS):
        step = at.join(at.select(F.col("node").alias("current"), F.col("current").alias("further")), "current", "left")
        if not step.filter("further is not null").limit(1).count():
            break
        at = written(step.select("node", F.coalesce("further", "current").alias("current")))
    else:
        raise ValueError("amendments supersede each other in a cycle")
    return s.join(at.withColumnRenamed("current", "further"), "node", "left").select("node", "scope", "kind", "status", F.coalesce("further", "current").alias("current"))


def redirect(ids: DataFrame, status: DataFrame) -> DataFrame:
    """Current versions of ``ids`` (node); withdrawn ones go."""
    return ids.join(status.select("node", "current"), "node").filter("current is not null").select("node", "current")
