"""Exchange boundary: source identity, version conflicts, history pages, deletes."""

from __future__ import annotations

from collections.abc import Callable

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from evigraph.sources.pack import exists


def source_key(pages: DataFrame) -> DataFrame:
    """Pages with server, logical id, language as type and digest of the raw bytes."""
    return pages.withColumns({
        "server": F.regexp_extract("url", "://([^/?#]*)", 1), "logical": F.regexp_extract("url", r"://[^/]*/[a-z]*/?(\d+)", 1), "type": F.regexp_extract("url", r"://[^/]*/([a-z]+)/", 1), "digest": F.sha2("html", 256),
    })


def identity_key(keyed: DataFrame, tenant: str, organization: str, mapping: str) -> DataFrame:
    """The whole key of a source version: tenant, organization, server, type, logical id, version (the
    query's ``page`` where a url has one), digest and mapping version."""
    version = F.regexp_extract("url", r"[?&]page=(\d+)", 1)
    return keyed.withColumn("identity", F.struct(F.lit(tenant).alias("tenant"), F.lit(organization).alias("organization"), "server", "type", "logical", version.alias("version"), "digest", F.lit(mapping).alias("mapping")))


def quarantine(keyed: DataFrame) -> tuple[DataFrame, DataFrame]:
    """(accepted, quarantined): a version key with several digests is kept out, never overwritten."""
    n = keyed.groupBy("server", "logical").agg(F.count_distinct("digest").alias("digests"))
    j = keyed.join(n, ["server", "logical"])
    return j.filter("digests = 1"), j.filter("digests > 1")


def deletes(previous: DataFrame, now: DataFrame, key: str) -> DataFrame:
    """Rows of the previous snapshot that are gone: each becomes a retraction."""
    return previous.join(now.select(key), key, "left_anti").select(key, F.lit("retraction").alias("kind"))


def provenance(mapped: DataFrame, attestations: DataFrame) -> DataFrame:
    """Origin and importer attestations of each mapped capsule, side by side and never merged."""
    a = attestations.groupBy("subject").pivot("purpose", ["clinical_origin", "exchange_import"]).agg(F.count(F.lit(1)))
    return mapped.join(a.withColumnRenamed("subject", "capsule_id"), "capsule_id", "left").fillna(0)


def sync(pages: list[DataFrame], land: Callable[[DataFrame], None], checkpoint: Callable[[int], None], since: int = -1) -> int:
    """Land history pages after ``since``; the checkpoint moves only once a whole page has landed."""
    for k, page in enumerate(pages):
        if k <= since:
            continue
        land(page)
        checkpoint(k)
        since = k
    return since


def mark(spark: SparkSession, path: str, page: int) -> None:
    """Note that a page has landed."""
    spark.createDataFrame([(page,)], "page int").write.mode("append").parquet(path)


def checkpoint_of(spark: SparkSession, path: str) -> int:
    """The last page that landed; -1 before the first."""
    if not exists(spark, path):
        return -1
    return spark.read.schema("page int").parquet(path).agg(F.coalesce(F.max("page"), F.lit(-1))).first()[0]


def remap(snapshots: DataFrame, version: str) -> DataFrame:
    """A new mapping version gives new mapped ids for the same snapshots."""
    return snapshots.select("capsule_id", F.sha2(F.concat_ws("|", "capsule_id", F.lit(version)), 256).alias("mapped_id"), F.lit(version).alias("mapping_version"))
