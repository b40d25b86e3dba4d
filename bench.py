"""Headline timings: one JSON line. BENCH_SF_DIR and BENCH_CPUS choose the tables and the threads.

The corpus is all that belongs to a scope (subjects, orders, items, events, notes) and the dictionary.
``integrity`` checks and hashes all of it again; ``reindex`` writes objects, edges, tags, postings, status,
both active views and watermarks from the packs; ``reproject`` writes links of two rules, status and
views; ``scope_load`` is the median of 100 subjects' whole histories, ``search_resolve`` that of single
queries from words to documents and their scopes. Every measure runs once before it is timed but for
append and reindex."""

from __future__ import annotations

import json
import os
import time

from pyspark.sql import SparkSession
from pyspark.sql import functions as F

from evigraph.functions.canonical import CAPSULE
from evigraph.operators import clearance, search
from evigraph.operators import links as L
from evigraph.plans import projection
from evigraph.plans.baselines import laid_out
from evigraph.plans.store import path_for, written
from evigraph.sources import ingest, pack
from evigraph.workloads import corpus, event_nodes, event_status, event_tags, item_tags, user_watermarks

BUCKETS = 128


def main() -> None:
    sf = os.environ.get("BENCH_SF_DIR", "/root/testdata/sf0.1")
    cpus = os.environ.get("BENCH_CPUS", "8")
    spark = (
        SparkSession.builder.master(f"local[{cpus}]").config("spark.sql.shuffle.partitions", cpus).config("spark.driver.memory", "12g")
        .config("spark.sql.session.timeZone", "UTC").config("spark.ui.enabled", "false").config("spark.ui.showConsoleProgress", "false").getOrCreate()
    )
    spark.sparkContext.setLogLevel("ERROR")
    out: dict[str, float] = {}
    more: dict[str, object] = {}

    def timed(name: str, run):
        t = time.perf_counter()
        r = run()
        out[name] = round(time.perf_counter() - t, 3)
        return r

    def median_of(name: str, runs: list) -> None:
        for run in runs[:3]:
            run()
        times = []
        for run in runs:
            t = time.perf_counter()
            run()
            times.append(time.perf_counter() - t)
        out[name] = round(sorted(times)[len(times) // 2], 4)

    store = path_for(spark, "packs")
    capsules = written(corpus(spark, sf))
    timed("append", lambda: pack.append(capsules, store, dedupe=False, buckets=BUCKETS))
    packed = spark.read.parquet(store)
    more["capsules"] = packed.count()
    size = laid_out(packed).first()
    more["pack_files"], more["pack_bytes_a_capsule"] = size["files"], round(size["bytes"] / size["objects"], 1)
    pack.verify_full(packed).collect()
    more["integrity_result"] = list(timed("integrity", lambda: pack.verify_full(packed).first()))

    def reindex() -> dict[str, int]:
        return {name: written(df).count() for name, df in pack.reindex(packed).items()}

    more["index_rows"] = timed("reindex", reindex)

    def reproject() -> dict[str, int]:
        links = L.derive(item_tags(spark, sf), L.R3, "both").select("link_id").unionByName(L.derive(event_tags(spark, sf), L.R1, "both").select("link_id"))
        views = pack.reindex(packed)
        made = {"links": links, "status": event_status(spark, sf), "problems": views["problems"], "therapies": views["therapies"]}
        return {name: written(df).count() for name, df in made.items()}

    reproject()
    more["projected_rows"] = timed("reproject", reproject)
    roots = [r["capsule_id"] for r in ingest.subjects(spark, sf).select("capsule_id", "c_custkey").orderBy(F.sha2(F.col("c_custkey").cast("string"), 256)).limit(100).collect()]
    own = packed.select(*CAPSULE, "pack_seq", "pack_bucket", "scope_root")
    median_of("scope_load", [lambda r=r: pack.load_scope(own, r, BUCKETS).collect() for r in roots])
    docs = ingest.read(spark, sf, "documents")
    n = spark.read.parquet(f"{sf}/customer.parquet").count()
    index = written(search.postings_table(docs.select("doc_id", "text"), docs.select("doc_id", (F.col("doc_id") % n).alias("scope")))).cache()
    more["postings"] = index.count()
    phrases = [r["text"] for r in ingest.read(spark, sf, "benchmark").orderBy("item_id").collect()][:40]
    median_of("search_resolve", [lambda p=p: search.resolve_text(index, p, 1) for p in phrases])
    more["search_found"] = sum(bool(search.resolve_text(index, p, 1)) for p in phrases[:3])

    # operational load: lag and recovery of a scope-local store, cost of clearance
    tags, marks = written(event_tags(spark, sf)), written(user_watermarks(spark, sf))
    derived = projection.Store(spark)
    projection.project_scopes(derived, tags, marks.withColumn("watermark", F.when(F.col("scope") % 5 == 0, F.col("watermark") - 1).otherwise(F.col("watermark"))), [L.R1], "g1")
    more["lagging_scopes"] = projection.mismatched(marks, derived.state()).count()
    timed("recovery", lambda: projection.recover(derived, tags, marks, [L.R1], "g1").count())
    links, nodes = written(derived.links()), written(event_nodes(spark, sf))
    timed("links_all", lambda: links.select("src", "dst").write.format("noop").mode("overwrite").save())
    timed("links_cleared", lambda: clearance.edges(links.select("src", "dst"), clearance.visible(nodes, clearance.Caller("nurse"))).write.format("noop").mode("overwrite").save())
    print(json.dumps({"metric": "evidence_graph_seconds", "value": round(sum(out[k] for k in ("integrity", "reindex", "reproject")), 3), "unit": "sec", "queries": out, "sf": sf, **more}))


if __name__ == "__main__":
    main()
