"""Packs: append-only framed capsules, clustered by scope.

A pack is a Parquet dataset partitioned by a bucket of the scope; frames carry a dense sequence number
per scope and a checksum. Many scopes share a file, so the file count follows the data, not the scopes.
"""

from __future__ import annotations

from pyspark.sql import DataFrame, SparkSession, Window
from pyspark.sql import functions as F

from evigraph.functions.canonical import CAPSULE, rehash
from evigraph.operators import status
from evigraph.operators.search import terms
from evigraph.operators.structure import dangling, spine_edges
from evigraph.plans.store import bounded, written

BUCKETS = 64


def bucket(scope, n: int = BUCKETS):
    return F.pmod(F.xxhash64(scope), F.lit(n)).cast("int")


def frames(capsules: DataFrame, after: DataFrame | None = None, buckets: int = BUCKETS) -> DataFrame:
    """Framed capsules: bucket, dense sequence per scope (after the stored watermark), checksum, length."""
    w = Window.partitionBy("pack_bucket", "scope_root").orderBy("recorded_us", "capsule_id")
    out = capsules.select(CAPSULE).withColumn("pack_bucket", bucket(F.col("scope_root"), buckets)).withColumn("pack_seq", F.row_number().over(w).cast("long"))
    if after is not None:
        out = out.join(after.select("scope_root", "watermark"), "scope_root", "left").withColumn("pack_seq", F.col("pack_seq") + F.coalesce("watermark", F.lit(0))).drop("watermark")
    content = F.concat_ws("|", "capsule_id", "kind", "body", F.col("clinical_us").cast("string"), F.array_join("parents", ","), "amends", "retracts", "author_id")
    return out.select(*CAPSULE, "pack_seq", F.crc32(content).alias("frame_crc"), F.length(content).alias("frame_len"), "pack_bucket")


def distinct_ids(capsules: DataFrame) -> DataFrame:
    """One capsule of each id. Only those whose id's hash occurs again are dealt out to meet."""
    hashed = capsules.withColumn("_h", F.xxhash64("capsule_id"))
    again = bounded(written(hashed.groupBy("_h").agg(F.count("*").alias("n")).filter("n > 1").select("_h")))
    return hashed.join(again, "_h", "left_anti").unionByName(hashed.join(again, "_h", "left_semi").dropDuplicates(["capsule_id"])).drop("_h")


def append(capsules: DataFrame, store: str, dedupe: bool = True, buckets: int = BUCKETS) -> DataFrame:
    """Append frames; content that is stored already is left out. Returns what was appended."""
    spark = capsules.sparkSession
    capsules = distinct_ids(capsules)
    after = None
    if exists(spark, store):
        old = spark.read.parquet(store)
        if dedupe:
            capsules = capsules.withColumn("pack_bucket", bucket(F.col("scope_root"), buckets)).join(old.select("pack_bucket", "capsule_id"), ["pack_bucket", "capsule_id"], "left_anti").drop("pack_bucket")
        after = watermarks(old)
    new = frames(capsules, after, buckets)
    # a first append is dealt by bucket once, and its frames are numbered where they lie
    laid = new.repartition("pack_bucket") if after is not None else frames(capsules.repartition(bucket(F.col("scope_root"), buckets)), None, buckets)
    laid.sortWithinPartitions("pack_bucket", "scope_root", "pack_seq").write.mode("append").option("compression", "zstd").partitionBy("pack_bucket").parquet(store)
    return new


def exists(spark: SparkSession, path: str) -> bool:
    p = spark._jvm.org.apache.hadoop.fs.Path(path)
    return p.getFileSystem(spark._jsc.hadoopConfiguration()).exists(p)


def watermarks(packed: DataFrame) -> DataFrame:
    return packed.groupBy("scope_root").agg(F.max("pack_seq").alias("watermark"))


def verify(packed: DataFrame) -> DataFrame:
    """Frames whose checksum or content id does not hold; a map over the scan."""
    content = F.concat_ws("|", "capsule_id", "kind", "body", F.col("clinical_us").cast("string"), F.array_join("parents", ","), "amends", "retracts", "author_id")
    out = packed.withColumn("bad_crc", F.crc32(content) != F.col("frame_crc")).withColumn("bad_id", rehash(packed) != F.col("capsule_id"))
    return out.filter("bad_crc or bad_id").select("capsule_id", "scope_root", "bad_crc", "bad_id")


def verify_full(packed: DataFrame) -> DataFrame:
    """One row: frames, bad checksums, bad ids, missing parents."""
    content = F.concat_ws("|", "capsule_id", "kind", "body", F.col("clinical_us").cast("string"), F.array_join("parents", ","), "amends", "retracts", "author_id")
    one = packed.agg(F.count("*").alias("frames"), F.sum((F.crc32(content) != F.col("frame_crc")).cast("long")).alias("bad_crc"), F.sum((rehash(packed) != F.col("capsule_id")).cast("long")).alias("bad_id"))
    return one.crossJoin(dangling(packed).agg(F.count("*").alias("missing_parents")))


def load_scope(packed: DataFrame, root: str, buckets: int = BUCKETS, large: bool = False) -> DataFrame:
    """A scope's whole history in order; prunes to its bucket, and in it by the order that files are
    sorted in. The scope is read and sorted in one task, as one subject's history is small; ``large``
    sorts one that is not over many."""
    own = packed.filter((F.col("pack_bucket") == bucket(F.lit(root), buckets)) & (F.col("scope_root") == root))
    return own.orderBy("pack_seq") if large else own.coalesce(1).sortWithinPartitions("pack_seq")


def get(packed: DataFrame, ids: DataFrame) -> DataFrame:
    """Capsules by (scope_root, capsule_id), pruned by bucket."""
    return packed.join(ids.withColumn("pack_bucket", bucket(F.col("scope_root"))), ["pack_bucket", "scope_root", "capsule_id"], "left_semi")


def recover(packed: DataFrame) -> DataFrame:
    """The valid prefix of each scope: frames before the first gap of the sequence or bad checksum."""
    content = F.concat_ws("|", "capsule_id", "kind", "body", F.col("clinical_us").cast("string"), F.array_join("parents", ","), "amends", "retracts", "author_id")
    w = Window.partitionBy("scope_root").orderBy("pack_seq")
    broken = (F.col("pack_seq") != F.row_number().over(w)) | (F.crc32(content) != F.col("frame_crc"))
    out = packed.withColumn("broken", broken.cast("int")).withColumn("before", F.max("broken").over(w.rowsBetween(Window.unboundedPreceding, 0)))
    return out.filter("before = 0").drop("broken", "before")


#: Kinds whose bodies hold words to search.
WORDED = ("subject", "episode", "note", "tag_dictionary")


def field(name: str):
    return F.get_json_object("body", f"$.{name}")


def tagging(packed: DataFrame) -> DataFrame:
    """(part, brand, class) of the dictionary that is packed."""
    return packed.filter("kind = 'tag_dictionary'").filter(field("table") == "part").select(field("key").alias("part"), field("brand").alias("brand"), field("class").alias("class"))


def reindex(packed: DataFrame, tags_of: DataFrame | None = None) -> dict[str, DataFrame]:
    """Everything that frames alone can give again: objects, parent edges, tags (over the dictionary that is
    packed too, or ``tags_of``, the :func:`tagging` of one that lies in other packs), postings of the words in
    bodies, record status, both active views, watermarks."""
    kind = lambda *names: packed.filter(F.col("kind").isin(*names))
    part = tagging(packed) if tags_of is None else tags_of
    # by shuffle: a table's size on disk says little of its rows
    tagged = kind("item").select("capsule_id", field("part").alias("part")).join(part.hint("merge"), "part")
    tags = tagged.select("capsule_id", F.explode(F.array(*(F.struct(F.lit(n).alias("ns"), F.col(n).alias("code")) for n in ("brand", "class")))).alias("t")).select("capsule_id", "t.ns", "t.code")
    text = kind(*WORDED).select("capsule_id", F.explode(F.array_distinct(terms(F.col("body")))).alias("term"))
    target = F.when(F.col("amends") != "", F.col("amends")).when(F.col("retracts") != "", F.col("retracts"))
    observed = kind("signal", "amendment", "retraction").select(
        F.col("capsule_id").alias("node"), F.col("scope_root").alias("scope"), F.col("clinical_us").alias("us"), "kind", target.alias("target"), (field("k").cast("int") % 2 == 0).alias("attested"))
    latest = F.row_number().over(Window.partitionBy("scope_root", field("priority")).orderBy(F.desc("clinical_us"), F.desc(field("key").cast("long"))))
    episodes = kind("episode").withColumn("r", latest).filter("r = 1")
    return {
        "objects": packed.select("capsule_id", "kind", "scope_root"), "edges": spine_edges(packed), "tags": tags, "text": text,
        "status": status.resolve(observed).select("node", "status", "current"),
        "problems": episodes.filter(field("status") == "O").select("scope_root", field("priority").alias("category"), "capsule_id"),
        "therapies": kind("item").filter((field("state") == "O") & (field("flag") != "R")).select("scope_root", "capsule_id"),
        "watermarks": watermarks(packed),
    }


#: What tells the rows of each of these apart.
KEYS = {
    "objects": ["capsule_id", "kind", "scope_root"], "edges": ["child", "parent"], "tags": ["capsule_id", "ns", "code"], "text": ["capsule_id", "term"], "status": ["node", "status", "current"],
    "problems": ["scope_root", "category", "capsule_id"], "therapies": ["scope_root", "capsule_id"], "watermarks": ["scope_root", "watermark"],
}


def copied(packed: DataFrame, path: str) -> DataFrame:
    """A copy of packs, laid out as they are."""
    packed.sortWithinPartitions("pack_bucket", "scope_root", "pack_seq").write.option("compression", "zstd").partitionBy("pack_bucket").parquet(path)
    return packed.sparkSession.read.parquet(path)
