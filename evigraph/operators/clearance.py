"""Clearance, tenants and contamination boundaries."""

from __future__ import annotations

from dataclasses import dataclass

from pyspark.sql import DataFrame
from pyspark.sql import functions as F

#: Level that each role may see.
ROLES = {"researcher": 0, "nurse": 1, "clinician": 2, "auditor": 2}


@dataclass(frozen=True)
class Caller:
    role: str
    tenant: int | None = None
    purpose: str = "care"
    emergency: bool = False

    @property
    def level(self) -> int:
        return max(ROLES.values()) if self.emergency else ROLES.get(self.role, -1)


def map_labels(labels: DataFrame, levels: dict[str, int]) -> DataFrame:
    """Local levels of source labels; a label without a mapping gets the highest."""
    pairs = F.create_map(*(F.lit(x) for kv in levels.items() for x in kv))
    return labels.withColumn("level", F.coalesce(pairs[F.col("label")], F.lit(max(levels.values(), default=2))))


def visible(nodes: DataFrame, caller: Caller) -> DataFrame:
    out = nodes.filter(F.col("level") <= caller.level)
    return tenant_filter(out, caller) if caller.tenant is not None else out


def tenant_filter(nodes: DataFrame, caller: Caller) -> DataFrame:
    return nodes.filter(F.col("tenant") == caller.tenant)


def permitted(nodes: DataFrame, caller: Caller) -> DataFrame:
    """What level, tenant and purpose allow together: outside of care a node also needs the consent of its
    subject, where the table tells it; an emergency passes level and consent, never the tenant."""
    out = visible(nodes, caller)
    if caller.purpose != "care" and not caller.emergency and "consent" in nodes.columns:
        out = out.filter(F.coalesce("consent", F.lit(False)))
    return out


def emergency_log(caller: Caller, seen: DataFrame) -> DataFrame:
    """A row for each node that an emergency showed; no rows otherwise."""
    log = access_log(caller, seen)
    return log if caller.emergency else log.filter("false")


def edges(links: DataFrame, seen: DataFrame) -> DataFrame:
    """Links both ends of which are visible; others go whole."""
    ids = seen.select("node")
    return links.join(ids.withColumnRenamed("node", "src"), "src", "left_semi").join(ids.withColumnRenamed("node", "dst"), "dst", "left_semi")


def masked(links: DataFrame, seen: DataFrame) -> DataFrame:
    """The rejected alternative: keep the link and blank the hidden end, which still tells it exists."""
    ids = seen.select("node", F.lit(True).alias("ok"))
    j = links.join(ids.select(F.col("node").alias("src"), F.col("ok").alias("os")), "src", "left").join(ids.select(F.col("node").alias("dst"), F.col("ok").alias("od")), "dst", "left")
    return j.withColumns({"src_shown": F.when(F.col("os"), F.col("src")), "dst_shown": F.when(F.col("od"), F.col("dst"))})


def audit_view(truncated: DataFrame, caller: Caller) -> DataFrame:
    """Only an auditor sees which ids were left out for clearance; others get counts of what they may see."""
    return truncated if caller.role == "auditor" else truncated.filter("cause <> 'clearance'")


def access_log(caller: Caller, nodes: DataFrame) -> DataFrame:
    return nodes.select("node", F.lit(caller.role).alias("role"), F.lit(caller.purpose).alias("purpose"), F.lit(caller.emergency).alias("emergency"))


# contamination boundaries


def ingest_check(parents: DataFrame) -> DataFrame:
    """Boundary 1: (child, root of each parent, expected root) rows that disagree go to quarantine."""
    return parents.groupBy("child").agg(F.count_distinct("parent_root").alias("n"), F.min("parent_root").alias("root"), F.first("expected").alias("expected")).filter("n > 1 or root <> expected")


def link_check(links: DataFrame, roots: DataFrame) -> DataFrame:
    """Boundary 2: links whose ends or own scope differ in root."""
    r = roots.select("node", "root")
    j = links.join(r.select(F.col("node").alias("src"), F.col("root").alias("src_root")), "src", "left").join(r.select(F.col("node").alias("dst"), F.col("root").alias("dst_root")), "dst", "left")
    ok = (F.col("src_root") == F.col("dst_root")) & (F.col("src_root") == F.col("scope"))
    return j.filter(~F.coalesce(ok, F.lit(False)))


def scan(capsule_roots: DataFrame, spine: DataFrame, corrections: DataFrame, links: DataFrame) -> DataFrame:
    """Boundary 3, offline: violations per place over metadata, spine, corrections and links."""
    r = capsule_roots.select("node", "root")
    up = spine.join(r.select(F.col("node").alias("child"), F.col("root").alias("a")), "child").join(r.select(F.col("node").alias("parent"), F.col("root").alias("b")), "parent").filter("a <> b")
    fix = corrections.join(r.select("node", F.col("root").alias("a")), "node").join(r.select(F.col("node").alias("target"), F.col("root").alias("b")), "target").filter("a <> b")
    parts = [("metadata", r.filter("root is null")), ("spine", up), ("corrections", fix), ("links", link_check(links, capsule_roots))]
    out = None
    for name, df in parts:
        one = df.agg(F.count("*").alias("violations")).select(F.lit(name).alias("place"), "violations")
        out = one if out is None else out.unionByName(one)
    return out
