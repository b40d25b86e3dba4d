"""Merkle layers of capsules from the source tables. Children hash their parents' ids, so every layer
is one equi-join on the parent's key; threads of unbounded depth are read turn by turn."""

from __future__ import annotations

import hashlib
from functools import reduce

import pyarrow as pa
from pyspark.sql import Column, DataFrame, SparkSession, Window
from pyspark.sql import functions as F

from evigraph.functions.canonical import CAPSULE, capsules, micros, money
from evigraph.plans import store
from evigraph.plans.store import bounded

DAY_US = 86_400_000_000


def read(spark: SparkSession, sf_dir: str, name: str) -> DataFrame:
    return spark.read.parquet(f"{sf_dir}/{name}.parquet")


def parts(spark: SparkSession, d: str, *tables: str) -> list[tuple[int, int]]:
    """The parts (i, of how many) that subjects are dealt to with all that is theirs, by a hash of their key: so
    many that one has some ``PART_ROWS`` rows of the tables."""
    n = max(1, -(-sum(read(spark, d, t).count() for t in tables) // store.PART_ROWS))
    return [(i, n) for i in range(n)]


def owned(rows: DataFrame, key: str, part: tuple[int, int] | None) -> DataFrame:
    """Rows of the subjects of a part, told by the subject's key."""
    return rows if part is None or part[1] == 1 else rows.filter(F.pmod(F.xxhash64(F.col(key).cast("long")), F.lit(part[1])) == part[0])


def line_key() -> Column:
    """A number for a line of an order, to select by; others may share it."""
    return F.shiftleft(F.col("l_orderkey").cast("long"), 3).bitwiseOR(F.pmod(F.coalesce("l_linenumber", F.lit(0)), F.lit(8)).cast("long"))


def subjects(spark: SparkSession, d: str, part: tuple[int, int] | None = None) -> DataFrame:
    c = owned(read(spark, d, "customer"), "c_custkey", part)
    body = {"key": F.col("c_custkey"), "nation": F.col("c_nationkey"), "segment": F.col("c_mktsegment"), "balance": money(F.col("c_acctbal"))}
    return capsules(c, "subject", body, F.lit(0), keep=("c_custkey", "c_nationkey", "c_acctbal"))


def episodes(spark: SparkSession, d: str, only: DataFrame | None = None, part: tuple[int, int] | None = None) -> DataFrame:
    """Orders as capsules; ``only`` (line) names the lines whose orders are wanted."""
    o = owned(read(spark, d, "orders"), "o_custkey", part)
    if only is not None:
        wanted = only.select(F.shiftright("line", 3).alias("o_orderkey")).distinct()
        o = o.join(bounded(wanted), "o_orderkey", "left_semi")
    s = subjects(spark, d, part).select(F.col("capsule_id").alias("subject_id"), F.col("c_custkey").alias("o_custkey"))
    body = {"key": F.col("o_orderkey"), "status": F.col("o_orderstatus"), "priority": F.col("o_orderpriority"), "total": money(F.col("o_totalprice"))}
    return capsules(o.join(s, "o_custkey"), "episode", body, micros(F.col("o_orderdate")), F.array("subject_id"), F.col("subject_id"), keep=("o_orderkey", "o_custkey", "o_orderstatus", "o_orderpriority"))


def items(spark: SparkSession, d: str, only: DataFrame | None = None, part: tuple[int, int] | None = None) -> DataFrame:
    """Lines of orders as capsules; ``only`` (line: their :func:`line_key`) names those wanted. Of a part, other
    subjects' lines go before any is dealt out."""
    line = read(spark, d, "lineitem")
    if only is not None:
        line = line.withColumn("line", line_key()).join(bounded(only), "line", "left_semi").drop("line")
    if part is not None and part[1] > 1:
        own = owned(read(spark, d, "orders"), "o_custkey", part).select(F.col("o_orderkey").alias("l_orderkey"))
        line = line.join(bounded(own), "l_orderkey", "left_semi")
    e = episodes(spark, d, only, part).select(F.col("capsule_id").alias("episode_id"), F.col("scope_root").alias("root"), F.col("o_orderkey").alias("l_orderkey"), "o_custkey")
    body = {
        "line": F.col("l_linenumber"), "part": F.col("l_partkey"), "supplier": F.col("l_suppkey"), "quantity": money(F.col("l_quantity")), "price": money(F.col("l_extendedprice")),
        "discount": money(F.col("l_discount")), "tax": money(F.col("l_tax")), "flag": F.col("l_returnflag"), "state": F.col("l_linestatus"),
    }
    return capsules(line.join(e, "l_orderkey"), "item", body, micros(F.col("l_shipdate")), F.array("episode_id"), F.col("root"), keep=("l_orderkey", "l_partkey", "l_returnflag", "l_linestatus", "o_custkey"))


def star(spark: SparkSession, d: str, part: tuple[int, int] | None = None) -> DataFrame:
    return reduce(DataFrame.unionByName, (f(spark, d, part=part).select(CAPSULE) for f in (subjects, episodes, items)))


def observed(spark: SparkSession, d: str, part: tuple[int, int] | None = None) -> DataFrame:
    """Events with micros, the small number in their properties, and what they correct: a signup the
    latest earlier purchase of its user, an error the event right before it unless that is an error."""
    e = owned(read(spark, d, "events"), "user_id", part).withColumns({"us": micros(F.col("ts")), "k": F.get_json_object("props", "$.k").cast("int")})
    w = Window.partitionBy("user_id").orderBy("us", "event_id")
    before = w.rowsBetween(Window.unboundedPreceding, -1)
    e = e.withColumns({
        "purchase_before": F.last(F.when(F.col("event_type") == "purchase", F.col("event_id")), True).over(before),
        "previous": F.lag("event_id").over(w), "previous_type": F.lag("event_type").over(w),
    })
    return e.withColumns({
        "amended": F.when(F.col("event_type") == "signup", F.col("purchase_before")),
        "retracted": F.when((F.col("event_type") == "error") & (F.col("previous_type") != "error"), F.col("previous")),
    }).drop("purchase_before", "previous", "previous_type")


def signals(spark: SparkSession, d: str, part: tuple[int, int] | None = None) -> DataFrame:
    """Views, clicks and purchases, then amendments of purchases, then retractions of either."""
    s = subjects(spark, d, part).select(F.col("capsule_id").alias("subject_id"), F.col("c_custkey").alias("user_id"))
    e = observed(spark, d, part).join(s, "user_id")
    body = {"event": F.col("event_id"), "type": F.col("event_type"), "value": money(F.col("value")), "k": F.col("k")}
    keep = ("event_id", "user_id", "event_type", "k")
    at, parent, root = F.col("us"), F.array("subject_id"), F.col("subject_id")
    plain = capsules(e.filter(F.col("event_type").isin("view", "click", "purchase")), "signal", body, at, parent, root, keep=keep)
    target = plain.select(F.col("event_id").alias("amended"), F.col("capsule_id").alias("target"))
    amend = e.filter("event_type = 'signup'").join(target, "amended", "left")
    amend = capsules(amend, "amendment", body, at, parent, root, amends=F.coalesce("target", F.lit("")), keep=keep)
    made = plain.select("event_id", "capsule_id").unionByName(amend.select("event_id", "capsule_id"))
    gone = e.filter("event_type = 'error'").join(made.select(F.col("event_id").alias("retracted"), F.col("capsule_id").alias("target")), "retracted", "left")
    gone = capsules(gone, "retraction", body, at, parent, root, retracts=F.coalesce("target", F.lit("")), keep=keep)
    return plain.unionByName(amend).unionByName(gone)


def notes(spark: SparkSession, d: str, part: tuple[int, int] | None = None) -> DataFrame:
    """One note per document, under the subject doc_id mod number of subjects; the text is hashed where it is
    read, not held."""
    n = subjects(spark, d).agg(F.count("*").alias("subjects"))
    doc = owned(read(spark, d, "documents").crossJoin(F.broadcast(n)).withColumn("owner", F.col("doc_id") % F.col("subjects")), "owner", part)
    doc = doc.select("doc_id", "owner", "lang", "source", F.sha2("text", 256).alias("digest"))
    doc = doc.join(subjects(spark, d, part).select(F.col("capsule_id").alias("subject_id"), F.col("c_custkey").alias("owner")), "owner")
    body = {"doc": F.col("doc_id"), "digest": F.col("digest"), "lang": F.coalesce("lang", F.lit("")), "source": F.coalesce("source", F.lit(""))}
    return capsules(doc, "note", body, F.lit(0), F.array("subject_id"), F.col("subject_id"), keep=("doc_id",))


def dialogue_capsules(turns: DataFrame) -> DataFrame:
    """conv_id, head, n_turns: each turn hashes the head before it. Threads are dealt by their id and read in
    order; what is held of one is its head, so a thread may have any number of turns."""
    kind = dict(turns.dtypes)["conv_id"]
    rows = turns.select("conv_id", F.col("turn").cast("string").alias("said"), "turn", F.coalesce("role", F.lit("")).alias("role"), F.sha2(F.coalesce("text", F.lit("")), 256).alias("digest"))
    ordered = rows.repartition("conv_id").sortWithinPartitions("conv_id", "turn", "role", "digest").select("conv_id", "said", "role", "digest")

    def fold(batches):
        now, head, n, any_rows, kept = None, "", 0, False, []
        for batch in batches:
            for conv, said, role, digest in zip(*(batch.column(c).to_pylist() for c in ("conv_id", "said", "role", "digest")), strict=True):
                if any_rows and conv != now:
                    kept.append((now, head, n))
                    head, n = "", 0
                now, any_rows = conv, True
                head = hashlib.sha256("|".join(x for x in (head, said, role, digest) if x is not None).encode()).hexdigest()
                n += 1
            if kept:
                yield _threads(kept, batch.schema.field("conv_id").type)
                kept = []
        if any_rows:
            yield _threads([(now, head, n)], batch.schema.field("conv_id").type)

    return ordered.mapInArrow(fold, f"conv_id {kind}, head string, n_turns long")


def _threads(rows: list[tuple], kind: pa.DataType) -> pa.RecordBatch:
    conv, head, n = zip(*rows, strict=True)
    return pa.RecordBatch.from_arrays([pa.array(conv, kind), pa.array(head, pa.string()), pa.array(n, pa.int64())], names=["conv_id", "head", "n_turns"])


def dictionary(spark: SparkSession, d: str) -> DataFrame:
    """Shared knowledge rows as capsules without a scope: regions, nations, parts, suppliers."""
    parts = capsules(read(spark, d, "part"), "tag_dictionary", {"key": F.col("p_partkey"), "table": F.lit("part"), "brand": F.col("p_brand"), "class": F.col("p_type")}, F.lit(0), scope=F.lit(""))
    sup = capsules(read(spark, d, "supplier"), "tag_dictionary", {"key": F.col("s_suppkey"), "table": F.lit("supplier"), "nation": F.col("s_nationkey")}, F.lit(0), scope=F.lit(""))
    nat = capsules(read(spark, d, "nation"), "tag_dictionary", {"key": F.col("n_nationkey"), "table": F.lit("nation"), "name": F.col("n_name")}, F.lit(0), scope=F.lit(""))
    reg = capsules(read(spark, d, "region"), "tag_dictionary", {"key": F.col("r_regionkey"), "table": F.lit("region"), "name": F.col("r_name")}, F.lit(0), scope=F.lit(""))
    return reduce(DataFrame.unionByName, (x.select(CAPSULE) for x in (parts, sup, nat, reg)))


def snapshots(spark: SparkSession, d: str, mapping_version: str = "1") -> tuple[DataFrame, DataFrame]:
    """Source snapshots (raw digest and identity) and the capsules mapped from them."""
    p = read(spark, d, "pages").select("page_id", "url", F.sha2("html", 256).alias("digest"), F.regexp_extract("url", "://([^/?#]*)", 1).alias("server"), F.regexp_extract("url", r"/(\d+)", 1).alias("logical"), F.regexp_extract("html", "<h1>(.*?)</h1>", 1).alias("title"))
    snap = capsules(p, "snapshot", {"server": F.col("server"), "logical": F.col("logical"), "digest": F.col("digest")}, F.lit(0), keep=("page_id", "server", "logical", "digest", "title"))
    body = {"title": F.sha2("title", 256), "mapping": F.lit(mapping_version), "logical": F.col("logical")}
    mapped = capsules(snap.select(F.col("capsule_id").alias("snap"), "page_id", "title", "logical"), "mapped", body, F.lit(0), F.array("snap"), F.col("snap"), keep=("page_id",))
    return snap, mapped
