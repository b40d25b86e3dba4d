"""Identity across roots: candidates by exact copies, adjudication, federated views."""

from __future__ import annotations

from pyspark.sql import DataFrame, Window
from pyspark.sql import functions as F


def same_object(objects: DataFrame) -> DataFrame:
    """(content_id, owners): identical content keeps one id however many owners attest it; how many do."""
    return objects.groupBy("content_id").agg(F.count_distinct("owner").alias("owners")).filter("owners > 1")


def candidates(objects: DataFrame) -> DataFrame:
    """(a, b) owners of equal content: neighbours in order, so a group of n owners proposes n - 1 links and
    is never gathered in one row."""
    after = F.lead("owner").over(Window.partitionBy("content_id").orderBy("owner"))
    return objects.select("content_id", "owner").distinct().select(F.col("owner").alias("a"), after.alias("b")).filter("b is not null").distinct()


ASSERTION = "a long, b long, state string, at int, by string, digest string"


def _asserted(pairs: DataFrame, state: str, by: str, at: int) -> DataFrame:
    """Assertions of a state, each with the digest that its author signs."""
    said = F.sha2(F.concat_ws("|", F.col("a").cast("string"), F.col("b").cast("string"), F.lit(state), F.lit(at), F.lit(by)), 256)
    return pairs.select("a", "b", F.lit(state).alias("state"), F.lit(at).alias("at"), F.lit(by).alias("by"), said.alias("digest"))


def adjudicate(pairs: DataFrame, by: str, at: int) -> DataFrame:
    return _asserted(pairs, "approved", by, at)


def retract(pairs: DataFrame, by: str, at: int) -> DataFrame:
    return _asserted(pairs, "retracted", by, at)


def states(pairs: DataFrame, assertions: DataFrame) -> DataFrame:
    """The state of each candidate: that of its latest assertion whose digest holds, else ``candidate``."""
    said = F.sha2(F.concat_ws("|", F.col("a").cast("string"), F.col("b").cast("string"), "state", F.col("at").cast("string"), "by"), 256)
    latest = assertions.filter(said == F.col("digest")).groupBy("a", "b").agg(F.max_by("state", "at").alias("state"))
    return pairs.join(latest, ["a", "b"], "left").select("a", "b", F.coalesce("state", F.lit("candidate")).alias("state"))


def current(assertions: DataFrame) -> DataFrame:
    """Latest state per pair; only approved ones link."""
    return assertions.groupBy("a", "b").agg(F.max_by("state", "at").alias("state")).filter("state = 'approved'").select("a", "b")


def federated_scope(roots: DataFrame, approved: DataFrame, tenants: DataFrame, tenant: int | None = None) -> DataFrame:
    """(root, linked_root): a root and the roots that approved, unretracted assertions link it to, if the
    caller's tenant may see them."""
    both = approved.select(F.col("a").alias("root"), F.col("b").alias("linked_root")).unionByName(approved.select(F.col("b").alias("root"), F.col("a").alias("linked_root")))
    out = roots.join(both, "root").unionByName(roots.select("root", F.col("root").alias("linked_root")))
    if tenant is not None:
        out = out.join(tenants.filter(F.col("tenant") == tenant).select(F.col("root").alias("linked_root")), "linked_root", "left_semi")
    return out.select("root", "linked_root").distinct()
