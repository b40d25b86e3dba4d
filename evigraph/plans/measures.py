"""Cost, accuracy and invariance measures."""

from __future__ import annotations

import time
from collections.abc import Callable
from statistics import median

from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from evigraph.plans.projection import fingerprint


def corpus_counts(capsules: DataFrame) -> DataFrame:
    return capsules.groupBy("kind").agg(F.count("*").alias("n"), F.count_distinct("scope_root").alias("scopes"))


def ingest_failures(sources: int, capsules: DataFrame, dangling: DataFrame) -> DataFrame:
    """Source rows without a capsule, and capsules that fell back to another parent or none."""
    return capsules.agg((F.lit(sources) - F.count("*")).alias("failed")).crossJoin(dangling.agg(F.count("*").alias("fallbacks")))


def jaccard(a: DataFrame, b: DataFrame, keys: list[str]) -> DataFrame:
    """Sizes, overlap and Jaccard similarity (in parts per million) of two id sets."""
    x, y = a.select(*keys).distinct().withColumn("x", F.lit(1)), b.select(*keys).distinct().withColumn("y", F.lit(1))
    j = x.join(y, keys, "full_outer")
    c = j.agg(F.count("x").alias("n_a"), F.count("y").alias("n_b"), F.sum((F.col("x").isNotNull() & F.col("y").isNotNull()).cast("long")).alias("both"), F.count("*").alias("either"))
    return c.select("n_a", "n_b", "both", F.expr("case when either = 0 then 1000000 else (both * 1000000) div either end").alias("jaccard_ppm"))


def link_stability(build: Callable[[], DataFrame], settings: list[dict[str, str]]) -> list[tuple]:
    """Fingerprints of the link ids under several runtime settings; they must all agree."""
    out = []
    for s in settings:
        df = build()
        spark = df.sparkSession
        old = {k: spark.conf.get(k, None) for k in s}
        try:
            for k, v in s.items():
                spark.conf.set(k, v)
            out.append(tuple(fingerprint(build(), "link_id").first()))
        finally:
            for k, v in old.items():
                spark.conf.set(k, v) if v is not None else spark.conf.unset(k)
    return out


def reconstruction(a: dict[str, DataFrame], b: dict[str, DataFrame], keys: dict[str, list[str]]) -> dict[str, tuple[bool, int]]:
    """Of every derived table, whether it has the same id set after a rebuild from copied packs, and its rows."""
    both = {k: [tuple(r) for r in fingerprint(a[k], *keys[k]).unionAll(fingerprint(b[k], *keys[k])).collect()] for k in a}
    return {k: (x == y, x[0]) for k, (x, y) in both.items()}


def link_provenance(links: DataFrame) -> DataFrame:
    return links.agg(F.count("*").alias("links"), F.sum((F.col("rule_id").isNull() | F.col("run_id").isNull()).cast("long")).alias("unnamed"))


def locality(touched: DataFrame, scopes: DataFrame) -> DataFrame:
    return touched.agg(F.count_distinct("scope").alias("touched")).crossJoin(scopes.agg(F.count_distinct("scope").alias("total")))


def drain_inversions(pages: list[tuple[int, int]]) -> int:
    return sum(b < a for (a, _), (b, _) in zip(pages, pages[1:], strict=False))


def evidence_recall(found: DataFrame, truth: DataFrame) -> DataFrame:
    """Of the (item_id, doc_id) pairs that hold the evidence, how many were found, and the precision."""
    hit = found.select("item_id", "doc_id").join(truth.select("item_id", "doc_id"), ["item_id", "doc_id"], "left_semi")
    return truth.agg(F.count("*").alias("truth")).crossJoin(found.agg(F.count("*").alias("returned"))).crossJoin(hit.agg(F.count("*").alias("hits")))


def leakage(outputs: DataFrame, hidden: DataFrame, columns: list[str]) -> DataFrame:
    """Hidden ids that show in any of the columns."""
    shown = outputs.select(F.explode(F.array(*(F.col(c).cast("string") for c in columns))).alias("node")).filter("node is not null").distinct()
    return shown.join(hidden.select(F.col("node").cast("string").alias("node")), "node", "left_semi").agg(F.count("*").alias("leaked"))


def truncation(truncated: DataFrame) -> DataFrame:
    return truncated.groupBy("cause").agg(F.count("*").alias("refs"), F.count_distinct("anchor").alias("responses"))


def expansion_violations(reached: DataFrame, nodes: DataFrame, level: int) -> DataFrame:
    """One row: reached nodes (anchor, scope, node) outside their anchor's scope, above the caller's level,
    withdrawn, or superseded, of all that were reached."""
    j = reached.select("anchor", "scope", "node").distinct().join(nodes.select("node", F.col("scope").alias("own"), "level", "current"), "node", "left")
    count = lambda c: F.coalesce(F.sum(F.coalesce(c, F.lit(False)).cast("long")), F.lit(0)).cast("long")
    return j.agg(
        F.count("*").alias("reached"), count(F.col("own").isNull() | (F.col("own") != F.col("scope"))).alias("out_of_scope"), count(F.col("level") > level).alias("hidden"),
        count(F.col("own").isNotNull() & F.col("current").isNull()).alias("withdrawn"), count(F.col("current") != F.col("node")).alias("superseded"))


def support(truth: DataFrame, usable: DataFrame) -> DataFrame:
    """(truth, supported, ppm): of the passages that hold the evidence, those in a document that may be
    used; it stands in for what a model could be given, not for what one would say."""
    n = truth.select("item_id", "doc_id").join(usable.select("doc_id"), "doc_id", "left_semi").agg(F.count("*").alias("supported"))
    return truth.agg(F.count("*").alias("truth")).crossJoin(n).withColumn("ppm", F.expr("case when truth = 0 then 0 else (supported * 1000000) div truth end"))


def timed(run: Callable[[], object], repeats: int = 5) -> float:
    """Median seconds after one warm-up."""
    run()
    out = []
    for _ in range(repeats):
        t = time.perf_counter()
        run()
        out.append(time.perf_counter() - t)
    return median(out)
