"""Spine edges, closure, roots, chapters."""

from __future__ import annotations

from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from evigraph.plans.store import written


def spine_edges(capsules: DataFrame) -> DataFrame:
    return capsules.select(F.col("capsule_id").alias("child"), F.explode("parents").alias("parent"), "scope_root")


def dangling(capsules: DataFrame) -> DataFrame:
    """Edges whose parent is not stored."""
    return spine_edges(capsules).join(capsules.select(F.col("capsule_id").alias("parent")), "parent", "left_anti")


def check_dag(edges: DataFrame) -> DataFrame:
    """Nodes between cycles or on one: peel the nodes without remaining parents and those without
    remaining children until none is left to peel. Content ids make cycles impossible; the check is for
    edges of other origin."""
    left, size = written(edges.select("child", "parent").distinct()), -1
    while True:
        n = left.count()
        if n in (0, size):
            return left.select(F.col("child").alias("node")).distinct()
        size = n
        inner = left.join(left.select(F.col("child").alias("parent")).distinct(), "parent", "left_semi")
        left = written(inner.join(left.select(F.col("parent").alias("child")).distinct(), "child", "left_semi").select("child", "parent"))


def closure(seeds: DataFrame, edges: DataFrame, direction: str = "down", max_depth: int | None = None) -> DataFrame:
    """(seed, node, distance), each node at its least distance: an unrolled join per level up to
    ``max_depth``; without one level after level until nothing new is met, cycles or not."""
    if direction == "both":
        edges = edges.select("child", "parent").unionByName(edges.select(F.col("parent").alias("child"), F.col("child").alias("parent")))
    a, b = ("child", "parent") if direction == "up" else ("parent", "child")
    step = edges.select(F.col(a).alias("node"), F.col(b).alias("next"))
    out = front = seeds.select(F.col("seed"), F.col("seed").alias("node"), F.lit(0).alias("distance"))
    k = 0
    while max_depth is None or k < max_depth:
        k += 1
        front = front.join(step, "node").select("seed", F.col("next").alias("node"), F.lit(k).alias("distance")).distinct()
        if max_depth is None:
            front = written(front.join(out.select("seed", "node"), ["seed", "node"], "left_anti"))
            if not front.limit(1).count():
                break
        out = out.unionByName(front)
    return out.groupBy("seed", "node").agg(F.min("distance").alias("distance"))


def scope_of(capsules: DataFrame) -> DataFrame:
    """(capsule_id, roots): the roots found by going up to the end; more than one is a conflict. Each level
    is one join; a chain that never ends is an error."""
    edges = written(spine_edges(capsules).select(F.col("child").alias("node"), "parent"))
    up = written(capsules.select("capsule_id", F.col("capsule_id").alias("node")).distinct())
    top, seen = None, written(up)
    while True:
        step = up.join(edges, "node", "left")
        ends = written(step.filter("parent is null").select("capsule_id", F.col("node").alias("root")))
        top = ends if top is None else top.unionByName(ends)
        above = step.filter("parent is not null").select("capsule_id", F.col("parent").alias("node")).distinct()
        up = written(above.join(seen, ["capsule_id", "node"], "left_anti"))
        if not up.limit(1).count():
            return top.groupBy("capsule_id").agg(F.array_sort(F.collect_set("root")).alias("roots"))
        seen = seen.unionByName(up)


def chapters(items: DataFrame, episode: str, at: str, kind: str) -> DataFrame:
    """Per episode: count, first and last time, kinds, newest first by ``ordinal`` within the scope."""
    return items.groupBy("scope", episode).agg(F.count("*").alias("n"), F.min(at).alias("t_min"), F.max(at).alias("t_max"), F.array_join(F.array_sort(F.collect_set(kind)), ",").alias("kinds"))


def sessions(events: DataFrame, gap_us: int) -> DataFrame:
    """(user_id, session, n, t_min, t_max): a new session starts after a silence of ``gap_us`` or more."""
    from pyspark.sql import Window

    w = Window.partitionBy("user_id").orderBy("us", "event_id")
    fresh = F.coalesce((F.col("us") - F.lag("us").over(w) >= gap_us).cast("int"), F.lit(1))
    e = events.withColumn("fresh", fresh).withColumn("session", F.sum("fresh").over(w.rowsBetween(Window.unboundedPreceding, 0)))
    return e.groupBy("user_id", "session").agg(F.count("*").alias("n"), F.min("us").alias("t_min"), F.max("us").alias("t_max"))
