"""Queries over the given tables, one per method, variant, baseline, measure or operator, and for each
that SQL can express the SQL that must give the same rows."""

from __future__ import annotations

from collections.abc import Callable

from pyspark.sql import DataFrame, SparkSession, Window
from pyspark.sql import functions as F

from evigraph import oracles as O
from evigraph.functions.canonical import CAPSULE, micros, rehash
from evigraph.operators import clearance as CL
from evigraph.operators import links as L
from evigraph.operators import search, status, structure, trust
from evigraph.plans import baselines as B
from evigraph.plans import identity, measures, projection, retrieval
from evigraph.plans.store import bounded, passing, path_for, written
from evigraph.sources import exchange, ingest, pack
from evigraph.streaming import flows

Query = Callable[[SparkSession, str], DataFrame]
QUERIES: dict[str, Query] = {}
ORACLE_SQL: dict[str, str] = {}
DAY = L.DAY_US


def query(sql: str | None = None, name: str | None = None) -> Callable[[Query], Query]:
    def add(f: Query) -> Query:
        QUERIES[name or f.__name__] = f
        if sql:
            ORACLE_SQL[name or f.__name__] = sql
        return f

    return add


# shared inputs


def event_nodes(s: SparkSession, d: str) -> DataFrame:
    """Events as nodes: node, scope, us, kind, target, attested, k, level, tokens."""
    e = ingest.observed(s, d)
    kind = F.when(F.col("event_type") == "signup", "amendment").when(F.col("event_type") == "error", "retraction").otherwise("signal")
    return e.select(
        F.col("event_id").alias("node"), F.col("user_id").alias("scope"), "us", "event_type", kind.alias("kind"), F.coalesce("amended", "retracted").alias("target"), (F.col("k") % 2 == 0).alias("attested"), "k",
        F.when(F.col("k") >= 90, 2).when(F.col("k") >= 70, 1).otherwise(0).alias("level"), (F.lit(5) + F.col("k") % 7).cast("long").alias("tokens"),
    )


def event_tags(s: SparkSession, d: str) -> DataFrame:
    e = event_nodes(s, d).filter("kind = 'signal'")
    return e.select("node", "scope", "us", "k", F.lit("etype").alias("ns"), F.col("event_type").alias("code"))


def star_items(s: SparkSession, d: str, only: DataFrame | None = None) -> DataFrame:
    part = ingest.read(s, d, "part").select(F.col("p_partkey").alias("l_partkey"), "p_brand", "p_type")
    return ingest.items(s, d, only).join(part, "l_partkey")


def lines_meeting(s: SparkSession, d: str, rule: L.LinkRule) -> DataFrame:
    """(line) of the lines that may be in a pair of ``rule`` over brand and class: found by small numbers alone,
    before any id is made. Brand and class are one short hash, times are days; what that blurs only lets
    more through."""
    part = ingest.read(s, d, "part").select(F.col("p_partkey").alias("l_partkey"), F.pmod(F.hash("p_brand", "p_type"), F.lit(1 << 20)).alias("kind"))
    line = ingest.read(s, d, "lineitem").select(ingest.line_key().alias("line"), "l_orderkey", "l_partkey", F.floor(micros(F.col("l_shipdate")) / F.lit(DAY)).cast("int").alias("day"))
    o = ingest.read(s, d, "orders").select(F.col("o_orderkey").alias("l_orderkey"), F.col("o_custkey").alias("scope"))
    j = line.join(bounded(part, 2_000_000), "l_partkey").select("line", "l_orderkey", "kind", "day").join(o.hint("merge"), "l_orderkey").drop("l_orderkey")
    near = j if rule.window_us is None else L.neighboured(j, ["scope", "kind"], "day", rule.window_us // DAY + 1)
    return written(near.select("line").distinct())


def item_tags(s: SparkSession, d: str, rule: L.LinkRule | None = None) -> DataFrame:
    """Brands and classes of the lines; with a rule that needs both to be shared, of those that it may link."""
    i = star_items(s, d, lines_meeting(s, d, rule) if rule else None).select(F.col("capsule_id").alias("node"), F.col("o_custkey").alias("scope"), F.col("clinical_us").alias("us"), F.col("l_orderkey").alias("k"), F.explode(F.array(F.struct(F.lit("brand").alias("ns"), F.col("p_brand").alias("code")), F.struct(F.lit("class").alias("ns"), F.col("p_type").alias("code")))).alias("t"))
    return i.select("node", "scope", "us", "k", "t.ns", "t.code")


def event_status(s: SparkSession, d: str, **kw) -> DataFrame:
    return status.resolve(event_nodes(s, d), **kw)


def r1_scored(s: SparkSession, d: str, rule: L.LinkRule = L.R1) -> DataFrame:
    return L.score(L.candidates(event_tags(s, d), rule), rule)


PAIR = ("scope", "src", "dst", "score")

# identity and capsules


@query(O.SUBJ + "SELECT c_custkey AS key, id AS capsule_id FROM subj")
def capsule_ids_subject(s, d):
    return ingest.subjects(s, d).select(F.col("c_custkey").alias("key"), "capsule_id")


@query(O.EPI + "SELECT o_orderkey AS key, id AS capsule_id, root AS scope_root FROM epi")
def capsule_ids_episode(s, d):
    return ingest.episodes(s, d).select(F.col("o_orderkey").alias("key"), "capsule_id", "scope_root")


@query(O.ITEM + "SELECT l_orderkey AS key, id AS capsule_id, root AS scope_root FROM item")
def capsule_ids_item(s, d):
    return ingest.items(s, d).select(F.col("l_orderkey").alias("key"), "capsule_id", "scope_root")


@query(O.SIG + "SELECT event_id, id AS capsule_id FROM sig")
def capsule_ids_signal(s, d):
    return ingest.signals(s, d).filter("kind = 'signal'").select("event_id", "capsule_id")


@query(O.CORR + "SELECT event_id, kind, id AS capsule_id, amends, retracts FROM amd UNION ALL SELECT event_id, kind, id, amends, retracts FROM rtr")
def capsule_ids_correction(s, d):
    return ingest.signals(s, d).filter("kind <> 'signal'").select("event_id", "kind", "capsule_id", "amends", "retracts")


@query(O.THREADS + "SELECT conv_id, head, n AS n_turns FROM chain WHERE i = n")
def thread_heads(s, d):
    return ingest.dialogue_capsules(ingest.read(s, d, "conversations"))


@query(O.NOTES + "SELECT doc_id, id AS capsule_id FROM note")
def note_capsules(s, d):
    return ingest.notes(s, d).select("doc_id", "capsule_id")


@query("SELECT page_id, regexp_extract(url, '://([^/?#]*)', 1) AS server, sha256(html) AS digest FROM pages")
def snapshot_mapped(s, d):
    snap, mapped = ingest.snapshots(s, d)
    return snap.join(mapped.select(F.element_at("parents", 1).alias("capsule_id"), F.col("capsule_id").alias("m")), "capsule_id").select("page_id", "server", "digest")


@query("SELECT sha256(text) AS content_id, count(*) AS copies FROM documents WHERE text IS NOT NULL GROUP BY 1 HAVING count(*) > 1")
def duplicate_content(s, d):
    return ingest.read(s, d, "documents").filter("text is not null").groupBy(F.sha2("text", 256).alias("content_id")).agg(F.count("*").alias("copies")).filter("copies > 1")


@query("SELECT count(*) AS n, count(*) FILTER (c_custkey % 10 = 0) AS flagged, count(*) FILTER (c_custkey % 10 = 0) AS changed FROM customer")
def tamper_probe(s, d):
    c = ingest.subjects(s, d).withColumn("hit", F.col("c_custkey") % 10 == 0).withColumn("body", F.when(F.col("hit"), F.concat("body", F.lit(" "))).otherwise(F.col("body")))
    return c.agg(F.count("*").alias("n"), F.sum((rehash(c) != F.col("capsule_id")).cast("long")).alias("flagged"), F.sum(F.col("hit").cast("long")).alias("changed"))


@query("SELECT 'episode' AS kind, count(*) AS n, count(DISTINCT o_custkey) AS scopes FROM orders UNION ALL SELECT 'item', count(*), count(DISTINCT o_custkey) FROM lineitem JOIN orders ON l_orderkey = o_orderkey UNION ALL SELECT 'subject', count(*), count(*) FROM customer")
def corpus_counts(s, d):
    return measures.corpus_counts(ingest.star(s, d))


@query("SELECT (SELECT count(*) FROM customer) + (SELECT count(*) FROM orders) + (SELECT count(*) FROM lineitem) - ((SELECT count(*) FROM customer) + (SELECT count(*) FROM orders JOIN customer ON o_custkey = c_custkey) + (SELECT count(*) FROM lineitem JOIN orders ON l_orderkey = o_orderkey)) AS failed, 0 AS fallbacks")
def ingest_failures(s, d):
    n = sum(ingest.read(s, d, t).count() for t in ("customer", "orders", "lineitem"))
    c = written(ingest.star(s, d))
    return measures.ingest_failures(n, c, structure.dangling(c))


# packs


@query(O.STAR + "SELECT id AS capsule_id, row_number() OVER (PARTITION BY root ORDER BY us, id) AS pack_seq FROM star")
def pack_frames(s, d):
    return pack.frames(ingest.star(s, d)).select("capsule_id", "pack_seq")


@query()
def frame_crc(s, d):
    return pack.frames(ingest.star(s, d)).groupBy("pack_bucket").agg(F.count("*").alias("frames"), F.bit_xor("frame_crc").alias("crc"), F.sum("frame_len").alias("chars"))


@query("SELECT (SELECT count(*) FROM customer) + (SELECT count(*) FROM orders) + (SELECT count(*) FROM lineitem) AS frames, 0 AS bad_crc, 0 AS bad_id, 0 AS missing_parents")
def verify_clean(s, d):
    return pack.verify_full(written(pack.frames(ingest.star(s, d))))


@query(O.STAR + "SELECT count(*) AS kept FROM (SELECT row_number() OVER (PARTITION BY root ORDER BY us, id) AS q FROM star) WHERE q < 5")
def torn_tail(s, d):
    f = pack.frames(ingest.star(s, d)).filter("pack_seq <> 5")  # the fifth frame of each scope is lost
    return pack.recover(f).agg(F.count("*").alias("kept"))


@query(O.STAR + "SELECT id AS capsule_id, row_number() OVER (ORDER BY us, id) AS pack_seq FROM star WHERE root = (SELECT id FROM subj WHERE c_custkey = 1)")
def scope_history(s, d):
    f = pack.frames(ingest.star(s, d))
    root = ingest.subjects(s, d).filter("c_custkey = 1").first()["capsule_id"]
    return pack.load_scope(f, root).select("capsule_id", "pack_seq")


@query("SELECT (SELECT count(*) FROM customer) + (SELECT count(*) FROM orders) + (SELECT count(*) FROM lineitem) AS object_files, (SELECT count(*) FROM customer) AS scopes, ceil(((SELECT count(*) FROM customer) + (SELECT count(*) FROM orders) + (SELECT count(*) FROM lineitem)) / 100000.0)::BIGINT AS pack_files")
def layout_files_vs_packs(s, d):
    return B.layout_stats(pack.frames(ingest.star(s, d)), 100_000).drop("chars")


@query("SELECT count(*) AS second_append FROM customer WHERE false")
def idempotent_append(s, d):
    c, store = ingest.subjects(s, d).select(CAPSULE), path_for(s, "pack")
    pack.append(c, store)
    return pack.append(c, store).agg(F.count("*").alias("second_append"))


def scoped(s, d, part=None):
    """All capsules that have a scope, or those of a part of the subjects."""
    return ingest.star(s, d, part).unionByName(ingest.signals(s, d, part).select(CAPSULE)).unionByName(ingest.notes(s, d, part).select(CAPSULE))


def corpus(s, d):
    """All capsules that have a scope, and the dictionary they refer to."""
    return scoped(s, d).unionByName(ingest.dictionary(s, d))


_FAMILIES = """, ev AS (SELECT st.* FROM st JOIN obs ON event_id = node JOIN customer ON c_custkey = user_id), notes AS (SELECT doc_id FROM documents, (SELECT count(*) AS n FROM customer) JOIN customer ON c_custkey = doc_id % n),
words AS (SELECT (SELECT count(*) FROM customer) + (SELECT count(*) FROM orders) + (SELECT count(*) FROM notes) + (SELECT count(*) FROM part) + (SELECT count(*) FROM supplier) + (SELECT count(*) FROM nation) + (SELECT count(*) FROM region) AS n)
SELECT 'objects' AS family, true AS same, n + (SELECT count(*) FROM lineitem) + (SELECT count(*) FROM ev) AS n FROM words
UNION ALL SELECT 'edges', true, (SELECT count(*) FROM orders) + (SELECT count(*) FROM lineitem) + (SELECT count(*) FROM ev) + (SELECT count(*) FROM notes)
UNION ALL SELECT 'tags', true, 2 * count(*) FROM lineitem JOIN part ON p_partkey = l_partkey
UNION ALL SELECT 'text', true, n FROM words
UNION ALL SELECT 'status', true, count(*) FROM ev WHERE status <> 'current'
UNION ALL SELECT 'problems', true, count(*) FROM (SELECT *, row_number() OVER (PARTITION BY o_custkey, o_orderpriority ORDER BY o_orderdate DESC, o_orderkey DESC) AS r FROM orders) WHERE r = 1 AND o_orderstatus = 'O'
UNION ALL SELECT 'therapies', true, count(*) FROM lineitem WHERE l_linestatus = 'O' AND l_returnflag <> 'R'"""


@query(O.STATUS + _FAMILIES)
def reconstruction(s, d):
    """Copy the packs, rebuild seven families from the copy, and hold ids and counts against what the
    sources give: first of the dictionary, then of one part of the subjects after the other, whose capsules,
    packs and copies go once they were compared. All that a family joins is of one subject, or the dictionary."""
    same, n = dict.fromkeys(pack.KEYS, True), dict.fromkeys(pack.KEYS, 0)

    def rebuilt(c, copied_tags=None, given_tags=None):
        c, store = written(c, "zstd"), path_for(s, "pack")
        pack.append(c, store, buckets=8)
        copy = pack.copied(s.read.parquet(store), path_for(s, "copy"))
        a, b = pack.reindex(copy, copied_tags), pack.reindex(pack.frames(c), given_tags)
        found = measures.reconstruction(a, b, pack.KEYS)
        counted = {"text": a["text"].select("capsule_id").distinct().count(), "status": a["status"].filter("status <> 'current'").count()}
        for k, (equal, rows) in found.items():
            same[k], n[k] = same[k] and equal, n[k] + counted.get(k, rows)
        return copy, c

    with passing(s):
        tags = [written(pack.tagging(x), "zstd") for x in rebuilt(ingest.dictionary(s, d))]
        for part in ingest.parts(s, d, "customer", "orders", "lineitem", "events", "documents"):
            with passing(s):
                rebuilt(scoped(s, d, part), *tags)
    return s.createDataFrame([(k, same[k], n[k]) for k in same if k != "watermarks"], "family string, same boolean, n long")


# structure


@query(O.ITEM + "SELECT id AS child, root AS parent FROM epi UNION ALL SELECT id, parent FROM item")
def spine_edges(s, d):
    return structure.spine_edges(ingest.star(s, d)).select("child", "parent")


@query(O.EPI + "SELECT id AS seed, id AS node, 0 AS distance FROM subj UNION ALL SELECT root, id, 1 FROM epi")
def spine_closure(s, d):
    sub, epi = ingest.subjects(s, d), ingest.episodes(s, d)
    return structure.closure(sub.select(F.col("capsule_id").alias("seed")), structure.spine_edges(epi), "down", 1)


@query("SELECT o_custkey AS scope, o_orderkey AS episode, count(l_orderkey) AS n, min(epoch_us(l_shipdate)) AS t_min, max(epoch_us(l_shipdate)) AS t_max, string_agg(DISTINCT l_returnflag, ',' ORDER BY l_returnflag) AS kinds FROM orders JOIN lineitem ON l_orderkey = o_orderkey GROUP BY 1, 2")
def episode_chapters(s, d):
    i = ingest.items(s, d).select(F.col("o_custkey").alias("scope"), F.col("l_orderkey").alias("episode"), F.col("clinical_us").alias("at"), F.col("l_returnflag").alias("kind"))
    return structure.chapters(i, "episode", "at", "kind")


@query("SELECT count(*) AS dangling FROM lineitem WHERE l_orderkey NOT IN (SELECT o_orderkey FROM orders)")
def dangling_parents(s, d):
    return structure.dangling(ingest.star(s, d)).agg(F.count("*").alias("dangling"))


@query("SELECT 1 AS roots, (SELECT count(*) FROM customer) + (SELECT count(*) FROM orders) AS n")
def multi_root(s, d):
    c = written(ingest.subjects(s, d).select(CAPSULE).unionByName(ingest.episodes(s, d).select(CAPSULE)))
    return structure.scope_of(c).groupBy(F.size("roots").alias("roots")).agg(F.count("*").alias("n"))


@query(O.OBS + """, m AS (SELECT user_id, us, event_id, CASE WHEN us - lag(us) OVER (PARTITION BY user_id ORDER BY us, event_id) < 21600000000 THEN 0 ELSE 1 END AS fresh FROM obs),
g AS (SELECT user_id, us, sum(fresh) OVER (PARTITION BY user_id ORDER BY us, event_id ROWS UNBOUNDED PRECEDING) AS session FROM m)
SELECT user_id, CAST(session AS BIGINT) AS session, count(*) AS n, min(us) AS t_min, max(us) AS t_max FROM g GROUP BY ALL""")
def sessions_6h(s, d):
    return structure.sessions(ingest.observed(s, d), 6 * 3_600_000_000)


@query("SELECT 0 AS cyclic")
def dag_check(s, d):
    return structure.check_dag(structure.spine_edges(ingest.episodes(s, d))).agg(F.count("*").alias("cyclic"))


@query("SELECT count(*) AS max_depth_pairs, 2 AS depth FROM lineitem JOIN orders ON l_orderkey = o_orderkey")
def dag_depth(s, d):
    c = structure.closure(ingest.subjects(s, d).select(F.col("capsule_id").alias("seed")), structure.spine_edges(ingest.star(s, d)), "down", 2)
    return c.filter("distance = 2").agg(F.count("*").alias("max_depth_pairs"), F.max("distance").alias("depth"))


# status


@query(O.STATUS + "SELECT node, status, coalesce(current, -1) AS current FROM st")
def record_status(s, d):
    return event_status(s, d).select("node", "status", F.coalesce("current", F.lit(-1)).alias("current"))


@query(O.STATUS_AS_OF + "SELECT node, status, coalesce(current, -1) AS current FROM st")
def status_as_of(s, d):
    return event_status(s, d, as_of=O.AS_OF).select("node", "status", F.coalesce("current", F.lit(-1)).alias("current"))


@query(O.OBS + ", a AS (SELECT amended AS target, event_id, us FROM obs WHERE amended IS NOT NULL AND k % 2 = 0) SELECT target, count(*) AS n, arg_max(event_id, us) AS current FROM a GROUP BY 1 HAVING count(*) > 1")
def competing_amendments(s, d):
    c = status.valid_corrections(event_nodes(s, d)).filter("kind = 'amendment' and attested")
    return status.winner(c).filter("n > 1").select("target", "n", "current")


@query(O.STATUS + "SELECT node FROM st WHERE status = 'pending_amendment'")
def pending_amendments(s, d):
    return event_status(s, d).filter("status = 'pending_amendment'").select("node")


@query(O.STATUS + "SELECT event_type, status, count(*) AS n FROM st JOIN obs ON event_id = node GROUP BY 1, 2")
def status_histogram(s, d):
    e = event_nodes(s, d)
    return status.resolve(e).join(e.select("node", "event_type"), "node").groupBy("event_type", "status").agg(F.count("*").alias("n"))


@query(O.OBS + "SELECT count(*) AS bad FROM obs WHERE false")
def bad_correction_targets(s, d):
    return status.bad_targets(event_nodes(s, d)).agg(F.count("*").alias("bad"))


@query("SELECT o_custkey AS scope, count(*) AS therapies FROM lineitem JOIN orders ON l_orderkey = o_orderkey WHERE l_linestatus = 'O' AND l_returnflag <> 'R' GROUP BY 1")
def active_therapies(s, d):
    return ingest.items(s, d).filter("l_linestatus = 'O' and l_returnflag <> 'R'").groupBy(F.col("o_custkey").alias("scope")).agg(F.count("*").alias("therapies"))


@query("SELECT o_custkey AS scope, o_orderpriority AS category, o_orderkey AS node FROM (SELECT *, row_number() OVER (PARTITION BY o_custkey, o_orderpriority ORDER BY o_orderdate DESC, o_orderkey DESC) AS r FROM orders) WHERE r = 1 AND o_orderstatus = 'O'")
def active_problems(s, d):
    e = ingest.episodes(s, d)
    r = F.row_number().over(Window.partitionBy("o_custkey", "o_orderpriority").orderBy(F.desc("clinical_us"), F.desc("o_orderkey")))
    return e.withColumn("r", r).filter("r = 1 and o_orderstatus = 'O'").select(F.col("o_custkey").alias("scope"), F.col("o_orderpriority").alias("category"), F.col("o_orderkey").alias("node"))


@query(O.STATUS + "SELECT node, current FROM st JOIN obs ON event_id = node WHERE event_type = 'purchase' AND current IS NOT NULL")
def redirect_current(s, d):
    e = event_nodes(s, d)
    return status.redirect(e.filter("event_type = 'purchase'").select("node"), status.resolve(e))


# tags and links


@query(O.ITEM + "SELECT id AS node, 'brand' AS ns, p_brand AS code FROM item JOIN part ON p_partkey = l_partkey UNION ALL SELECT id, 'class', p_type FROM item JOIN part ON p_partkey = l_partkey")
def tags_star(s, d):
    return item_tags(s, d).select("node", "ns", "code")


@query("SELECT user_id AS scope, 'etype' AS ns, event_type AS code, count(*) AS f FROM events WHERE event_type IN ('view', 'click', 'purchase') GROUP BY ALL")
def tag_frequency(s, d):
    return L.tag_frequency(event_tags(s, d))


@query("SELECT user_id AS scope, event_type AS code, count(*) AS n FROM events WHERE event_type IN ('view', 'click', 'purchase') GROUP BY ALL HAVING count(*) BETWEEN 2 AND 12")
def tag_bounds(s, d):
    return L.bound_tags(event_tags(s, d), 2, 12).groupBy("scope", "code").agg(F.count("*").alias("n"))


@query(O.R1 + "SELECT scope, src, dst, score FROM cand")
def link_candidates_r1(s, d):
    return r1_scored(s, d).select(*PAIR)


def _capped(mode: str) -> Query:
    return lambda s, d: L.cap(r1_scored(s, d), L.R1.cap, mode).select(*PAIR)


for _mode, _sql in (("source", "r1n <= 3"), ("both", "r1n <= 3 AND r2n <= 3"), ("either", "r1n <= 3 OR r2n <= 3")):
    query(O.R1_RANKED + f"SELECT scope, src, dst, score FROM ranked WHERE {_sql}", f"links_r1_{_mode}")(_capped(_mode))
query(None, "links_r1_greedy")(_capped("greedy"))


@query()
def links_r1_greedy_rounds(s, d):
    return L.greedy_rounds(r1_scored(s, d).select("scope", "src", "dst", "score"), L.R1.cap)


@query(O.R2_RANKED + "SELECT scope, src, dst, score FROM ranked WHERE r1n <= 2 AND r2n <= 2")
def links_r2_both(s, d):
    return L.cap(r1_scored(s, d, L.R2), L.R2.cap, "both").select(*PAIR)


@query(O.R3 + "SELECT scope, src, dst, shared, score FROM cand")
def links_r3(s, d):
    c = L.candidates(item_tags(s, d, L.R3), L.R3).filter("src_k <> dst_k")
    return L.score(c, L.R3).select("scope", "src", "dst", "shared", "score")


def r4_pairs(s, d):
    i = ingest.items(s, d)
    a = i.filter("l_returnflag = 'R'").select(F.col("o_custkey").alias("scope"), "l_partkey", F.col("capsule_id").alias("src"), F.col("clinical_us").alias("src_us"), F.col("l_orderkey").alias("o1"))
    b = i.select(F.col("o_custkey").alias("scope"), "l_partkey", F.col("capsule_id").alias("dst"), F.col("clinical_us").alias("dst_us"), F.col("l_orderkey").alias("o2"))
    j = a.join(b, ["scope", "l_partkey"]).filter("o1 <> o2 and dst_us > src_us").withColumn("shared", F.lit(1))
    return L.score(j.withColumn("tag", F.concat(F.lit("part:"), F.col("l_partkey").cast("string"))), L.R4)


@query(O.R4 + "SELECT scope, src, dst, score FROM r4")
def links_r4_warning(s, d):
    return r4_pairs(s, d).select(*PAIR)


@query(O.R4 + "SELECT 'accepted' AS outcome, '' AS reason, count(*) AS n FROM r4 HAVING count(*) > 0 UNION ALL SELECT 'rejected', 'evidence', count(*) FROM r4 HAVING count(*) > 0")
def gate_rejects(s, d):
    p = written(r4_pairs(s, d))
    good = L.identify(p, L.R4).withColumn("evidence_id", F.col("tag"))
    bare = L.identify(p, L.R5, rule_id="R5").withColumn("evidence_id", F.lit(""))
    known = ingest.read(s, d, "part").select(F.concat(F.lit("part:"), F.col("p_partkey").cast("string")).alias("evidence_id"))
    ok, no = L.escalation_gate(good.unionByName(bare), known)
    return ok.groupBy(F.lit("accepted").alias("outcome"), F.lit("").alias("reason")).agg(F.count("*").alias("n")).unionByName(no.groupBy(F.lit("rejected").alias("outcome"), "reason").agg(F.count("*").alias("n")))


@query(O.R3 + "SELECT scope, src, dst, 2 AS n_rules FROM cand")
def rival_rules(s, d):
    c = written(L.score(L.candidates(item_tags(s, d, L.R3), L.R3).filter("src_k <> dst_k"), L.R3))
    both = L.identify(c, L.R3).unionByName(L.identify(c, L.R6))
    return L.consolidate(both).select("scope", "src", "dst", F.col("n_rules").cast("long").alias("n_rules"))


@query(O.R1_RANKED + f"SELECT scope, src, dst, 'co_occurs' AS relation, '{L.R1.rule_id()}' AS rules, score FROM ranked WHERE r1n <= 3 AND r2n <= 3")
def consolidated(s, d):
    return L.consolidate(L.derive(event_tags(s, d), L.R1)).select("scope", "src", "dst", "relation", "rules", "score")


@query(O.R1_RANKED + f"SELECT sha256(concat_ws('|', src, dst, 'co_occurs', tag, '{L.R1.rule_id()}')) AS link_id, link_us FROM ranked WHERE r1n <= 3 AND r2n <= 3")
def link_ids(s, d):
    return L.derive(event_tags(s, d), L.R1).select("link_id", "link_us")


@query(O.R1_RANKED + "SELECT coalesce(tag, '') AS tag, coalesce(scope % 10, -1) AS shard, grouping(tag, scope % 10) AS g, count(*) AS n FROM ranked WHERE r1n <= 3 AND r2n <= 3 GROUP BY GROUPING SETS ((tag, scope % 10), (tag), ())")
def link_histogram(s, d):
    x = L.derive(event_tags(s, d), L.R1).withColumn("shard", F.col("scope") % 10)
    return x.groupingSets([["tag", "shard"], ["tag"], []], "tag", "shard").agg(F.grouping_id().cast("long").alias("g"), F.count("*").alias("n")).fillna("", ["tag"]).fillna(-1, ["shard"])


@query(O.R1_RANKED + "SELECT count(*) AS links, 0 AS unnamed FROM ranked WHERE r1n <= 3 AND r2n <= 3")
def link_provenance(s, d):
    return measures.link_provenance(L.derive(event_tags(s, d), L.R1, run_id="run"))


@query("SELECT 1000000 AS jaccard_ppm")
def link_stability(s, d):
    a = L.derive(event_tags(s, d), L.R1)
    b = L.derive(event_tags(s, d).repartition(13, "k"), L.R1)
    return measures.jaccard(written(a), written(b), ["link_id"]).select("jaccard_ppm")


# projection and rolling


@query(O.R1_RANKED + """, r2c AS (SELECT * FROM ranked WHERE gap <= 259200000000), two AS (SELECT *, row_number() OVER (PARTITION BY scope, node ORDER BY score2 DESC, src, dst) AS r FROM (
SELECT scope, src, dst, 10 * (100 - abs(k1 - k2)) + 100 - (100 * gap) // 259200000000 AS score2, unnest([src, dst]) AS node FROM r2c)),
n2 AS (SELECT scope, src, dst FROM two WHERE r <= 2 GROUP BY ALL HAVING count(*) = 2), n1 AS (SELECT scope, src, dst FROM ranked WHERE r1n <= 3 AND r2n <= 3)
SELECT CASE WHEN a.src IS NULL THEN 'added' WHEN b.src IS NULL THEN 'removed' ELSE 'kept' END AS change, count(*) AS n FROM n1 a FULL JOIN n2 b ON a.scope = b.scope AND a.src = b.src AND a.dst = b.dst GROUP BY 1""")
def generation_diff(s, d):
    a, b = (L.cap(r1_scored(s, d, r), r.cap, "both") for r in (L.R1, L.R2))
    return L.diff(a, b, ["scope", "src", "dst"]).groupBy("change").agg(F.count("*").alias("n"))


@query(f"SELECT 'links' AS projection, '{projection.CONTRACT}' AS contract, g AS generation, n AS n_rules, n AS runs FROM (VALUES ('g1', 1), ('g2', 2)) t(g, n)")
def manifest(s, d):
    """One run under g1, published twice, and two under g2, each of two rules: the store keeps a row a run."""
    store, tags = projection.Store(s), written(event_tags(s, d))
    marks = written(user_watermarks(s, d))
    for scopes, rules, generation in ((marks, [L.R1], "g1"), (marks, [L.R1], "g1"), (marks.filter("scope % 2 = 0"), [L.R1, L.R2], "g2"), (marks.filter("scope % 2 = 1"), [L.R2, L.R1], "g2")):
        projection.project_scopes(store, tags, scopes, rules, generation)
    return store.manifests().groupBy("projection", "contract", "generation", F.size("rule_ids").alias("n_rules")).agg(F.count("*").alias("runs"))


def user_watermarks(s, d):
    return event_nodes(s, d).groupBy("scope").agg(F.max("us").alias("watermark"))


def _late(s, d):
    """State that lags: every fifth user was projected without the last event."""
    w = Window.partitionBy("scope").orderBy(F.desc("us"), F.desc("node"))
    ranked = event_nodes(s, d).withColumn("r", F.row_number().over(w))
    return ranked.filter("scope % 5 <> 0 or r > 1").groupBy("scope").agg(F.max("us").alias("watermark"))


@query("WITH e AS (SELECT user_id, epoch_us(ts) AS us, row_number() OVER (PARTITION BY user_id ORDER BY ts DESC, event_id DESC) AS r FROM events), a AS (SELECT user_id, max(us) AS w FROM e GROUP BY 1), b AS (SELECT user_id, max(us) AS w FROM e WHERE user_id % 5 <> 0 OR r > 1 GROUP BY 1) SELECT a.user_id AS scope, a.w AS stored, b.w AS projected FROM a LEFT JOIN b ON a.user_id = b.user_id WHERE a.w IS DISTINCT FROM b.w")
def watermark_mismatch(s, d):
    return projection.mismatched(user_watermarks(s, d), _late(s, d))


@query(O.R1_RANKED + "SELECT scope, count(*) AS links FROM ranked WHERE r1n <= 3 AND r2n <= 3 GROUP BY 1")
def scope_local_replace(s, d):
    store, tags = projection.Store(s), written(event_tags(s, d))
    marks = written(user_watermarks(s, d))
    projection.project_scopes(store, tags.filter("us < 1706140800000000"), marks.withColumn("watermark", F.lit(0).cast("long")), [L.R1], "g1")
    projection.project_scopes(store, tags, marks, [L.R1], "g1")
    return store.links().groupBy("scope").agg(F.count("*").alias("links"))


@query("WITH e AS (SELECT DISTINCT user_id FROM events WHERE event_type IN ('view','click','purchase','signup','error')) SELECT count(*) FILTER (user_id % 5 = 0) AS caught_up, 0 AS left_over FROM e")
def recover(s, d):
    store, tags = projection.Store(s), written(event_tags(s, d))
    marks = written(user_watermarks(s, d))
    projection.project_scopes(store, tags, _late(s, d), [L.R1], "g1")
    late = projection.recover(store, tags, marks, [L.R1], "g1")
    return late.agg(F.count("*").alias("caught_up")).crossJoin(projection.mismatched(marks, store.state()).agg(F.count("*").alias("left_over")))


def _classed(s, d):
    o = ingest.read(s, d, "orders")
    horizon = o.agg(F.max(F.unix_micros(F.col("o_orderdate").cast("timestamp")))).first()[0]
    last = o.groupBy(F.col("o_custkey").alias("scope")).agg(F.max(F.unix_micros(F.col("o_orderdate").cast("timestamp"))).alias("last_us"))
    c = ingest.read(s, d, "customer").select(F.col("c_custkey").alias("scope"), (F.col("c_acctbal") < 0).alias("deceased"))
    return projection.priority(c.join(last, "scope", "left").withColumn("new_write", F.lit(False)), horizon)


@query(O.PRIO + "SELECT class, count(*) AS n FROM prio GROUP BY 1")
def priority_classes(s, d):
    return _classed(s, d).groupBy("class").agg(F.count("*").alias("n"))


def _migrated(s, d):
    return _classed(s, d).select("scope", F.when(F.col("scope") % 3 == 0, "g2").otherwise("g1").alias("generation"))


@query(O.PRIO + "SELECT scope, class FROM prio WHERE scope % 3 <> 0")
def virtual_backlog(s, d):
    return projection.backlog(_classed(s, d), _migrated(s, d), "g2").select("scope", "class")


@query(O.PRIO + "SELECT scope, class, row_number() OVER (ORDER BY class, sha256(CAST(scope AS VARCHAR))) AS place FROM prio WHERE scope % 3 <> 0 QUALIFY place <= 100")
def drain_plan(s, d):
    p = projection.page(projection.backlog(_classed(s, d), _migrated(s, d), "g2"), 100)
    return p.select("scope", "class", F.row_number().over(Window.orderBy("class", F.sha2(F.col("scope").cast("string"), 256))).alias("place"))


@query("SELECT count(DISTINCT user_id) AS drained, 0 AS inversions FROM events")
def drain_order(s, d):
    store, tags = projection.Store(s), written(event_tags(s, d))
    m = written(user_watermarks(s, d).withColumn("class", (F.lit(1) + F.col("scope") % 4).cast("int")))
    pages = projection.drain(store, tags, m, [L.R2], "g2", max(1, m.count() // 3 + 1))
    return s.createDataFrame([(sum(n for _, n in pages), measures.drain_inversions(pages))], "drained long, inversions long")


@query("SELECT c_custkey % 7 AS scope, count(*) AS attempts, arg_max(concat('e', c_custkey % 3), c_custkey) AS error, max(c_custkey) AS at_us FROM customer WHERE c_acctbal < 0 GROUP BY 1")
def retry_latest(s, d):
    f = ingest.read(s, d, "customer").filter("c_acctbal < 0").select((F.col("c_custkey") % 7).alias("scope"), F.concat(F.lit("e"), (F.col("c_custkey") % 3).cast("string")).alias("error"), F.col("c_custkey").alias("at_us"))
    return projection.retry_latest(f)


@query("SELECT c_custkey AS scope, CASE WHEN c_custkey % 3 = 0 THEN 'current' ELSE 'deny' END AS decision FROM customer")
def access_policy(s, d):
    return projection.access(_classed(s, d).select("scope"), _migrated(s, d), "g2", "deny_high_risk").select("scope", "decision")


@query("SELECT 0 AS foreign_inputs")
def lineage_lint(s, d):
    """Files in the plan that are no source tables, and inputs that capsules name which are no capsules."""
    star = ingest.star(s, d)
    bad = projection.lint_lineage(star, ["customer", "orders", "lineitem"])
    return structure.dangling(star).agg((F.count("*") + len(bad)).alias("foreign_inputs"))


# trust


def _keys(s, d) -> list[trust.Key]:
    """One key per nation, derived from the nation's number; some expired, revoked or narrowed."""
    rows = ingest.read(s, d, "nation").orderBy("n_nationkey").collect()
    out = []
    for r in rows:
        n = r["n_nationkey"]
        purposes = ("clinical_origin",) if n % 5 == 1 else trust.PURPOSES
        out.append(trust.Key(f"key{n}", n, trust.public_key(bytes([n]) * 32).hex(), purposes, (r["n_regionkey"],), 0, 500 if n % 5 == 2 else 1 << 62, 100 if n % 5 == 3 else None))
    return out


def _attestations(s, d, keys) -> DataFrame:
    rows = []
    for k in keys:
        for j, purpose in enumerate(trust.PURPOSES):
            a = list(trust.attest(f"rule{k.organization % 3}", purpose, k, bytes([k.organization]) * 32, f"actor{j}", 1000))
            if k.organization % 5 == 4 and j == 2:
                a[7] = a[7][:-2] + ("00" if a[7][-2:] != "00" else "01")  # a broken signature
            rows.append(tuple(a))
    return s.createDataFrame(rows, trust.ATTESTATION)


_POLICY = """WITH p AS (SELECT unnest(['clinical_origin', 'exchange_import', 'knowledge_release']) AS purpose), a AS (SELECT n_nationkey AS organization, n_regionkey AS tenant, purpose FROM nation, p),
v AS (SELECT organization, purpose, CASE WHEN tenant <> 1 THEN 'tenant' WHEN organization % 5 = 1 AND purpose <> 'clinical_origin' THEN 'purpose' WHEN organization % 5 = 2 THEN 'validity' WHEN organization % 5 = 3 THEN 'revoked' ELSE 'valid' END AS verdict FROM a)
"""


@query(_POLICY + "SELECT organization, purpose, verdict FROM v")
def attestation_policy_verdict(s, d):
    keys = _keys(s, d)
    return trust.policy_verdict(_attestations(s, d, keys), trust.key_table(s, keys), 1).select("organization", "purpose", "verdict")


@query(_POLICY + "SELECT CASE WHEN verdict = 'valid' AND organization % 5 = 4 AND purpose = 'knowledge_release' THEN 'signature' ELSE verdict END AS verdict, count(*) AS n FROM v GROUP BY 1")
def signature_verify(s, d):
    keys = _keys(s, d)
    return trust.verify(_attestations(s, d, keys), trust.key_table(s, keys), 1).groupBy("verdict").agg(F.count("*").alias("n"))


@query(_POLICY + "SELECT concat('rule', organization % 3) AS subject, count(DISTINCT organization) AS approvals, count(DISTINCT organization) >= 2 AS approved FROM v WHERE verdict = 'valid' AND purpose = 'clinical_origin' GROUP BY 1")
def release_quorum(s, d):
    keys = _keys(s, d)
    return trust.approved(trust.verify(_attestations(s, d, keys), trust.key_table(s, keys), 1), "clinical_origin", 2)


@query("SELECT CAST(i AS BIGINT) AS n, i = 0 AS active, CASE i WHEN 0 THEN 'ok' WHEN 1 THEN 'tampered' ELSE 'approvals' END AS reason FROM range(3) t(i)")
def release_revalidate(s, d):
    r = L.rule_capsules(s, [L.R1, L.R3, L.R4])
    order = {L.R1.rule_id(): 0, L.R3.rule_id(): 1, L.R4.rule_id(): 2}
    r = r.withColumn("body", F.when(F.col("rule_id") == L.R3.rule_id(), F.concat("body", F.lit(" "))).otherwise(F.col("body")))
    approvals = s.createDataFrame([(L.R1.rule_id(), 2, True), (L.R3.rule_id(), 2, True)], "subject string, approvals int, approved boolean")
    names = F.create_map(*(F.lit(x) for kv in order.items() for x in kv))
    return trust.revalidate(r, approvals).select(names[F.col("rule_id")].cast("long").alias("n"), "active", "reason")


@query("SELECT purpose, count(*) AS n FROM nation, (SELECT unnest(['clinical_origin', 'exchange_import', 'knowledge_release']) AS purpose) GROUP BY 1")
def purpose_separation(s, d):
    a = _attestations(s, d, _keys(s, d))
    out = None
    for p in trust.PURPOSES:
        one = trust.by_purpose(a, p).groupBy("purpose").agg(F.count("*").alias("n"))
        out = one if out is None else out.unionByName(one)
    return out


@query("SELECT n_nationkey AS organization, string_agg(n_regionkey, ',') AS tenants FROM nation GROUP BY 1")
def effective_policy(s, d):
    n = ingest.read(s, d, "nation").select(F.col("n_nationkey").alias("organization"), F.col("n_regionkey").alias("tenant"))
    return trust.effective_policy(n).select("organization", F.array_join("tenants", ",").alias("tenants"))


@query("SELECT concat('rule', n_nationkey % 3) AS subject, count(*) * 3 AS n, count(*) AS organizations FROM nation GROUP BY 1")
def attestations_of_subject(s, d):
    return trust.of_subject(_attestations(s, d, _keys(s, d))).select("subject", "n", F.size("organizations").cast("long").alias("organizations"))


# clearance


@query(O.NODES + "SELECT node FROM nodes WHERE level <= 1")
def visible_nodes(s, d):
    return CL.visible(event_nodes(s, d), CL.Caller("nurse")).select("node")


@query(O.R1_NODES + "SELECT kept.scope, src, dst FROM kept JOIN nodes a ON a.node = src JOIN nodes b ON b.node = dst WHERE a.level <= 1 AND b.level <= 1")
def visible_links(s, d):
    seen = CL.visible(event_nodes(s, d), CL.Caller("nurse"))
    return CL.edges(L.derive(event_tags(s, d), L.R1), seen).select("scope", "src", "dst")


@query(O.R1_NODES + "SELECT count(*) AS links, count(*) FILTER (a.level > 1 OR b.level > 1) AS masked, count(*) FILTER (a.level <= 1 AND b.level <= 1) AS removed_whole_left FROM kept JOIN nodes a ON a.node = src JOIN nodes b ON b.node = dst")
def masked_vs_removed(s, d):
    seen = CL.visible(event_nodes(s, d), CL.Caller("nurse"))
    m = CL.masked(L.derive(event_tags(s, d), L.R1), seen)
    hidden = F.col("src_shown").isNull() | F.col("dst_shown").isNull()
    return m.agg(F.count("*").alias("links"), F.sum(hidden.cast("long")).alias("masked"), F.sum((~hidden).cast("long")).alias("removed_whole_left"))


@query(O.NODES + "SELECT node, 'auditor' AS role, 'care' AS purpose, false AS emergency FROM nodes WHERE level = 2")
def audit_view(s, d):
    return CL.access_log(CL.Caller("auditor"), CL.visible(event_nodes(s, d), CL.Caller("auditor")).filter("level = 2"))


@query("SELECT 0 AS leaked")
def leakage(s, d):
    nodes = event_nodes(s, d)
    r = _context(s, d)
    hidden = nodes.filter("level > 1").select("node")
    return measures.leakage(r.nodes.select("node").unionByName(r.truncated.select("node")), hidden, ["node"])


@query("SELECT CASE WHEN quality = 0 THEN 1 WHEN toxic = 1 THEN 2 ELSE 0 END AS level, count(*) AS n FROM labels GROUP BY 1")
def map_labels(s, d):
    lab = ingest.read(s, d, "labels").select(F.when(F.col("quality") == 0, "junk").when(F.col("toxic") == 1, "toxic").otherwise("plain").alias("label"))
    return CL.map_labels(lab, {"plain": 0, "junk": 1, "toxic": 2}).groupBy("level").agg(F.count("*").alias("n"))


@query("SELECT c_custkey AS node FROM customer JOIN nation ON n_nationkey = c_nationkey WHERE n_regionkey = 2")
def tenant_isolation(s, d):
    c = ingest.read(s, d, "customer").join(F.broadcast(ingest.read(s, d, "nation")), F.col("c_nationkey") == F.col("n_nationkey"))
    return CL.tenant_filter(c.select(F.col("c_custkey").alias("node"), F.col("n_regionkey").alias("tenant")), CL.Caller("nurse", tenant=2)).select("node")


# retrieval


def _context_inputs(s, d):
    e = event_nodes(s, d)
    st = status.resolve(e)
    nodes = written(e.filter("kind = 'signal'").join(st.select("node", "current"), "node").select("node", "scope", "level", "current", "tokens", "us"))
    links = written(L.derive(event_tags(s, d), L.R1).select("scope", "src", "dst", F.lit(0).alias("rank_severity"), "score", "rule_id"))
    good = retrieval.live(nodes.filter("level <= 1"))
    anchors = good.groupBy("scope").agg(F.max_by("node", F.struct("us", "node")).alias("node")).select(F.col("scope").alias("anchor"), "scope", "node")
    return anchors, nodes, links


def _context(s, d, limits: retrieval.Limits = retrieval.Limits(), mode: str = "prefix"):  # noqa: B008
    return retrieval.retrieve_many(*_context_inputs(s, d), CL.Caller("nurse"), limits, mode)


@query(O.CONTEXT + "SELECT anchor, node, hop FROM got1")
def expand_one_hop(s, d):
    return _context(s, d).nodes.select("anchor", "node", "hop")


@query(O.CONTEXT + "SELECT anchor, node, hop FROM got2")
def expand_two_hop(s, d):
    return _context(s, d, retrieval.Limits(hops=2, per_node=512, total=512)).nodes.select("anchor", "node", "hop")


@query(O.CONTEXT + "SELECT anchor, node, 'depth' AS cause FROM beyond1")
def policy_truncation(s, d):
    return _context(s, d).truncated


@query(O.CONTEXT + "SELECT anchor, count(*) AS n_nodes, sum(tokens)::BIGINT AS tokens_used FROM (SELECT g.anchor, tokens, sum(tokens) OVER (PARTITION BY g.anchor ORDER BY hop, g.node ROWS UNBOUNDED PRECEDING) AS used FROM got1 g JOIN nodes n ON n.node = g.node) WHERE used <= 20 GROUP BY 1")
def token_budget_prefix(s, d):
    return _context(s, d, retrieval.Limits(tokens=20)).report.filter("n_nodes > 0").select("anchor", "n_nodes", "tokens_used")


@query()
def token_budget_skipfill(s, d):
    return _context(s, d, retrieval.Limits(tokens=20), "skip_fill").report.select("anchor", "n_nodes", "tokens_used", "n_token")


@query(O.CONTEXT + "SELECT a.anchor, (SELECT count(*) FROM got1 g WHERE g.anchor = a.anchor) AS n_nodes, (SELECT count(*) FROM beyond1 g WHERE g.anchor = a.anchor) AS n_policy, 0 AS n_token, NOT EXISTS (SELECT 1 FROM beyond1 g WHERE g.anchor = a.anchor) AS complete FROM anchors a")
def context_report(s, d):
    return _context(s, d).report.drop("tokens_used")


@query(O.CONTEXT + "SELECT anchor, 0 AS missing, 0 AS violations FROM anchors")
def completeness_check(s, d):
    inputs = tuple(_context_inputs(s, d))
    limits = retrieval.Limits()
    r = retrieval.retrieve_many(*inputs, CL.Caller("nurse"), limits)
    return retrieval.completeness(r, *inputs, CL.Caller("nurse"), limits).select("anchor", "missing", "violations")


@query(O.CONTEXT + "SELECT 'depth' AS cause, count(*) AS refs, count(DISTINCT anchor) AS responses FROM beyond1 HAVING count(*) > 0")
def truncation_causes(s, d):
    return measures.truncation(_context(s, d).truncated)


@query(O.CONTEXT + f", o AS (SELECT anchor, node, hop, row_number() OVER (PARTITION BY anchor ORDER BY hop, node) AS ord FROM got1) SELECT anchor, string_agg(node || '@' || hop || CASE WHEN hop = 0 THEN '(anchor)' ELSE '(link:{L.R1.rule_id()})' END, ';' ORDER BY ord) AS text FROM o GROUP BY 1")
def render_context(s, d):
    return retrieval.render(_context(s, d).nodes)


@query(O.STATUS_AS_OF + "SELECT user_id AS scope, arg_max(node, us) AS node, count(*) AS n FROM st JOIN obs ON event_id = node WHERE status = 'current' AND event_type IN ('view', 'click', 'purchase') GROUP BY 1")
def replay_as_of(s, d):
    e = event_nodes(s, d)
    st = status.resolve(e, as_of=O.AS_OF).filter("status = 'current' and kind = 'signal'")
    return st.select("node", "scope").join(e.select("node", "us"), "node").groupBy("scope").agg(F.max_by("node", "us").alias("node"), F.count("*").alias("n"))


def _owners(s, d):
    n = ingest.read(s, d, "customer").count()
    return ingest.read(s, d, "documents").filter("text is not null").select(F.sha2("text", 256).alias("content_id"), (F.col("doc_id") % n).alias("owner"))


_OWN = "WITH n AS (SELECT count(*) AS n FROM customer), o AS (SELECT DISTINCT sha256(text) AS content_id, doc_id % n AS owner FROM documents, n WHERE text IS NOT NULL), g AS (SELECT content_id, owner, lead(owner) OVER (PARTITION BY content_id ORDER BY owner) AS nxt FROM o), pair AS (SELECT DISTINCT owner AS a, nxt AS b FROM g WHERE nxt IS NOT NULL) "


@query(_OWN + "SELECT a, b FROM pair")
def identity_candidates(s, d):
    return identity.candidates(_owners(s, d))


@query(_OWN + "SELECT content_id, count(*) AS owners FROM o GROUP BY 1 HAVING count(*) > 1")
def same_object(s, d):
    return identity.same_object(_owners(s, d))


@query(_OWN + ", ok AS (SELECT a, b FROM pair WHERE (a + b) % 4 <> 3), l AS (SELECT a AS root, b AS linked_root FROM ok UNION SELECT b, a FROM ok UNION SELECT c_custkey, c_custkey FROM customer) SELECT root, linked_root FROM l WHERE root IN (SELECT c_custkey FROM customer)")
def federated_context(s, d):
    c = identity.candidates(_owners(s, d))
    said = c.select("a", "b", F.lit("approved").alias("state"), F.lit(1).alias("at")).unionByName(c.filter("(a + b) % 4 = 3").select("a", "b", F.lit("retracted").alias("state"), F.lit(2).alias("at")))
    roots = ingest.read(s, d, "customer").select(F.col("c_custkey").alias("root"))
    return identity.federated_scope(roots, identity.current(said), roots)


@query(O.CONTAINS + "SELECT item_id, count(*) AS n FROM truth GROUP BY 1")
def evidence_truth(s, d):
    return _truth(s, d).groupBy("item_id").agg(F.count("*").alias("n"))


_COSINE = """WITH v AS (SELECT vec_id, CAST(embedding AS DOUBLE[]) AS e FROM embeddings), c AS (SELECT a.vec_id AS query_id, b.vec_id, CAST(round(list_dot_product(a.e, b.e) / (sqrt(list_dot_product(a.e, a.e)) * sqrt(list_dot_product(b.e, b.e))) * 1000000) AS BIGINT) AS sim FROM v a JOIN v b ON a.vec_id <> b.vec_id WHERE a.vec_id % 20 = 0),
r AS (SELECT *, row_number() OVER (PARTITION BY query_id ORDER BY sim DESC, vec_id) AS rank FROM c) SELECT query_id, vec_id, sim, rank FROM r WHERE rank <= """
_BM25 = """WITH t AS (SELECT doc_id, [w FOR w IN string_split(lower(regexp_replace(coalesce(text, ''), '[^\\p{L}0-9]+', ' ', 'g')), ' ') IF w <> ''] AS ts FROM documents),
p AS (SELECT doc_id, len, term, count(*) AS tf FROM (SELECT doc_id, len(ts) AS len, unnest(ts) AS term FROM t) GROUP BY ALL), df AS (SELECT term, count(*) AS df FROM p GROUP BY 1), m AS (SELECT count(*) AS n, avg(len(ts)) AS mean FROM t),
q AS (SELECT DISTINCT item_id, unnest([w FOR w IN string_split(lower(regexp_replace(text, '[^\\p{L}0-9]+', ' ', 'g')), ' ') IF w <> '']) AS term FROM benchmark),
s AS (SELECT item_id, doc_id, CAST(sum(CAST(round(1000 * ln(1 + (n - df + 0.5) / (df + 0.5)) * tf * 2.2 / (tf + 1.2 * (0.25 + 0.75 * len / mean))) AS BIGINT)) AS BIGINT) AS score FROM q JOIN p USING (term) JOIN df USING (term), m GROUP BY 1, 2),
found AS (SELECT * FROM (SELECT *, row_number() OVER (PARTITION BY item_id ORDER BY score DESC, doc_id) AS rank FROM s) WHERE rank <= {k}) """


def _bm25(k: int) -> str:
    return _BM25.replace("{k}", str(k))


def _truth(s, d):
    docs, b = ingest.read(s, d, "documents").select("doc_id", F.col("text").alias("t")), ingest.read(s, d, "benchmark")
    words = lambda c: F.array_distinct(search.terms(F.coalesce(c, F.lit(""))))
    # candidates share the item's longest word; containment decides
    anchor = F.array_max(F.transform(words(F.col("text")), lambda w: F.struct(F.length(w).alias("n"), w.alias("w"))))["w"]
    q = b.select("item_id", "text", anchor.alias("w"))
    post = docs.select("doc_id", "t", F.explode(words(F.col("t"))).alias("w")).join(q, "w")
    return post.filter(F.contains("t", "text")).select("item_id", "doc_id").distinct()


@query(_bm25(5) + "SELECT item_id, doc_id, score, rank FROM found")
def fts_resolve(s, d):
    return B.lexical_rag(ingest.read(s, d, "documents"), ingest.read(s, d, "benchmark"), 5)


@query(_bm25(5) + ", truth AS (SELECT item_id, doc_id FROM benchmark b JOIN documents d ON contains(d.text, b.text)) SELECT (SELECT count(*) FROM truth) AS truth, (SELECT count(*) FROM found) AS returned, (SELECT count(*) FROM found SEMI JOIN truth USING (item_id, doc_id)) AS hits")
def evidence_recall(s, d):
    return measures.evidence_recall(B.lexical_rag(ingest.read(s, d, "documents"), ingest.read(s, d, "benchmark"), 5), _truth(s, d))


@query(_COSINE + "10")
def vector_topk(s, d):
    """Queries are the rows whose id is divisible by 20, against all rows."""
    v = ingest.read(s, d, "embeddings")
    return search.vector_topk(v, v.filter("vec_id % 20 = 0"), 10)


# exchange and contamination


@query("WITH p AS (SELECT page_id, regexp_extract(url, '://([^/?#]*)', 1) AS server, regexp_extract(url, '://[^/]*/[a-z]*/?(\\d+)', 1) AS logical, sha256(html) AS digest FROM pages) SELECT page_id FROM p WHERE (server, logical) IN (SELECT (server, logical) FROM p GROUP BY server, logical HAVING count(DISTINCT digest) > 1)")
def version_conflict_quarantine(s, d):
    return exchange.quarantine(exchange.source_key(ingest.read(s, d, "pages")))[1].select("page_id")


@query("SELECT page_id, 'retraction' AS kind FROM pages WHERE page_id % 10 = 0")
def delete_as_retraction(s, d):
    p = ingest.read(s, d, "pages").select("page_id")
    return exchange.deletes(p, p.filter("page_id % 10 <> 0"), "page_id")


@query("SELECT count(*) AS landed, 3 AS checkpoint FROM pages")
def sync_pages(s, d):
    from evigraph.plans.store import path_for

    p, out, marks = ingest.read(s, d, "pages"), path_for(s, "sync"), []
    exchange.sync([p.filter(F.col("page_id") % 4 == k) for k in range(4)], lambda x: x.write.mode("append").parquet(out), marks.append)
    return s.read.parquet(out).agg(F.count("*").alias("landed")).withColumn("checkpoint", F.lit(marks[-1]))


@query("SELECT count(*) AS snapshots, count(*) AS remapped FROM pages")
def remap_versions(s, d):
    snap, _ = ingest.snapshots(s, d)
    a, b = exchange.remap(snap, "1"), exchange.remap(snap, "2")
    return a.join(b.select("capsule_id", F.col("mapped_id").alias("m2")), "capsule_id").agg(F.count("*").alias("snapshots"), F.sum((F.col("mapped_id") != F.col("m2")).cast("long")).alias("remapped"))


@query("SELECT unnest(['metadata', 'spine', 'corrections', 'links']) AS place, 0 AS violations")
def contamination_scan(s, d):
    e = written(event_nodes(s, d))
    roots = e.select("node", F.col("scope").alias("root"))
    spine = e.filter("false").select(F.col("node").alias("child"), F.col("node").alias("parent"))
    return CL.scan(roots, spine, e.filter("target is not null").select("node", "target"), L.derive(event_tags(s, d), L.R1))


@query("SELECT l_orderkey % 50 AS child, count(DISTINCT o_custkey) AS n FROM lineitem JOIN orders ON l_orderkey = o_orderkey GROUP BY 1 HAVING count(DISTINCT o_custkey) > 1")
def ingest_root_check(s, d):
    i = ingest.items(s, d).select((F.col("l_orderkey") % 50).alias("child"), F.col("o_custkey").alias("parent_root"), F.col("o_custkey").alias("expected"))
    return CL.ingest_check(i).filter("n > 1").select("child", "n")


# baselines


@query(_COSINE + "5")
def base_vector_rag(s, d):
    v = ingest.read(s, d, "embeddings")
    return B.vector_rag(v, v.filter("vec_id % 20 = 0"), 5)


@query(_bm25(3) + "SELECT item_id, doc_id, score, rank FROM found")
def base_lexical_rag(s, d):
    return B.lexical_rag(ingest.read(s, d, "documents"), ingest.read(s, d, "benchmark"), 3)


@query()
def base_community_graph(s, d):
    return B.community_graph(B.entities(ingest.read(s, d, "documents"))).groupBy("community").agg(F.count("*").alias("entities"))


@query()
def base_community_reports(s, d):
    m = written(B.entities(ingest.read(s, d, "documents")))
    return B.community_reports(m, B.community_graph(m))


@query()
def base_community_update(s, d):
    docs = ingest.read(s, d, "documents")
    a = B.community_graph(B.entities(docs.filter("doc_id % 20 <> 7")))
    b = B.community_graph(B.entities(docs))
    return B.community_update(written(a), written(b))


@query(O.NODES + "SELECT scope AS anchor, count(*) AS n_nodes, sum(tokens)::BIGINT AS tokens_used FROM nodes GROUP BY 1")
def base_full_chart(s, d):
    n = event_nodes(s, d)
    return B.full_chart(n.select("scope", "node", "tokens"), n.select("scope", F.col("scope").alias("anchor")).distinct())


@query(O.NODES + "SELECT scope, node FROM (SELECT *, row_number() OVER (PARTITION BY scope ORDER BY us DESC, node DESC) AS r FROM nodes) WHERE r <= 10")
def base_recent_k(s, d):
    return B.recent_k(event_nodes(s, d), 10).select("scope", "node")


@query(O.NODES + "SELECT scope, CAST(to_json({'entry': list({'node': node, 'kind': kind, 'us': us} ORDER BY node)}) AS VARCHAR) AS bundle FROM nodes GROUP BY scope")
def base_bundle_serialization(s, d):
    return B.bundle_serialization(event_nodes(s, d))


@query(O.R1_RANKED + "SELECT count(*) AS links FROM ranked WHERE r1n <= 3 AND r2n <= 3")
def base_rebuild_all(s, d):
    return B.rebuild_all(event_tags(s, d), L.R1).agg(F.count("*").alias("links"))


@query(O.INCIDENT + "SELECT (SELECT count(*) FROM exact) AS exact, (SELECT count(*) FROM patched) AS patched, (SELECT count(*) FROM exact ANTI JOIN patched USING (scope, src, dst)) AS missing, (SELECT count(*) FROM patched ANTI JOIN exact USING (scope, src, dst)) AS stale")
def base_incident_only(s, d):
    t = written(event_tags(s, d))
    e, p = B.incident_only(t, t.filter("us >= 1706140800000000").select("node"), L.R1, "source")
    e, p = written(e.select("scope", "src", "dst")), written(p.select("scope", "src", "dst").distinct())
    k = ["scope", "src", "dst"]
    return e.agg(F.count("*").alias("exact")).crossJoin(p.agg(F.count("*").alias("patched"))).crossJoin(e.join(p, k, "left_anti").agg(F.count("*").alias("missing"))).crossJoin(p.join(e, k, "left_anti").agg(F.count("*").alias("stale")))


@query()
def base_incident_only_greedy(s, d):
    t = written(event_tags(s, d))
    e, p = B.incident_only(t, t.filter("us >= 1706140800000000").select("node"), L.R1, "greedy")
    return measures.jaccard(e, p, ["scope", "src", "dst"])


@query()
def base_unordered_cap(s, d):
    c = written(r1_scored(s, d))
    return measures.jaccard(B.unordered_cap(c, 3, 1), B.unordered_cap(c, 3, 2), ["scope", "src", "dst"])


_PAGES = "WITH u AS (SELECT count(DISTINCT user_id) AS n FROM events) SELECT 'at once' AS way, 1 AS transactions, n AS largest FROM u UNION ALL SELECT 'rolling', CAST(ceil(n / ceil(n / 4.0)) AS BIGINT), CAST(ceil(n / 4.0) AS BIGINT) FROM u"


@query(_PAGES)
def base_sync_migration(s, d):
    """One transaction over all scopes, against pages of a quarter of them."""
    tags, m = written(event_tags(s, d)), written(user_watermarks(s, d).withColumn("class", F.lit(2)))
    once, rolling = projection.Store(s), projection.Store(s)
    B.sync_migration(once, tags, m, [L.R2], "g2")
    projection.drain(rolling, tags, m, [L.R2], "g2", -(-m.count() // 4))
    return B.transactions(once).select(F.lit("at once").alias("way"), "*").unionByName(B.transactions(rolling).select(F.lit("rolling").alias("way"), "*"))


@query("SELECT count(*) AS queued_rows, count(*) FILTER (c_custkey % 3 <> 0) AS backlog FROM customer")
def base_materialized_queue(s, d):
    """Rows that a queue copies up front, those already at the target among them, and the backlog that a
    filter finds without copying."""
    c = _classed(s, d)
    return B.materialized_queue(c, "g2").agg(F.count("*").alias("queued_rows")).crossJoin(projection.backlog(c, _migrated(s, d), "g2").agg(F.count("*").alias("backlog")))


@query(O.R3 + "SELECT count(*) AS kept, count(*) AS lost FROM cand")
def base_last_rule_wins(s, d):
    c = written(L.score(L.candidates(item_tags(s, d, L.R3), L.R3).filter("src_k <> dst_k"), L.R3))
    both = L.identify(c, L.R3).unionByName(L.identify(c, L.R6))
    one = B.last_rule_wins(both)
    return both.agg(F.count("*").alias("all")).crossJoin(one.agg(F.count("*").alias("kept"))).select("kept", (F.col("all") - F.col("kept")).alias("lost"))


@query(O.R1_NODES + "SELECT count(*) AS leaked FROM kept JOIN nodes a ON a.node = src JOIN nodes b ON b.node = dst WHERE a.level > 1 OR b.level > 1")
def base_masked_edges(s, d):
    seen = CL.visible(event_nodes(s, d), CL.Caller("nurse"))
    return CL.masked(L.derive(event_tags(s, d), L.R1), seen).filter("src_shown is null or dst_shown is null").agg(F.count("*").alias("leaked"))


@query(ORACLE_SQL["generation_diff"])
def base_frozen_links(s, d):
    a, b = (L.cap(r1_scored(s, d, r), r.cap, "both") for r in (L.R1, L.R2))
    return B.frozen_links(a, b)


@query(O.R1_STATUS + "SELECT count(*) AS links, count(*) FILTER (a.status = 'retracted' OR b.status = 'retracted') AS retracted_served, count(*) FILTER (a.status = 'superseded' OR b.status = 'superseded') AS superseded_served FROM kept JOIN st a ON a.node = src JOIN st b ON b.node = dst")
def base_no_status(s, d):
    return B.no_status(L.derive(event_tags(s, d), L.R1), event_status(s, d))


@query(O.CONTEXT + "SELECT count(*) AS shown FROM (SELECT sum(tokens) OVER (PARTITION BY g.anchor ORDER BY hop, g.node ROWS UNBOUNDED PRECEDING) AS used FROM got1 g JOIN nodes n ON n.node = g.node) WHERE used <= 20")
def base_silent_budget(s, d):
    r = _context(s, d)
    return B.silent_budget(r.nodes, 20).agg(F.count("*").alias("shown"))


@query("WITH n AS (SELECT (SELECT count(*) FROM nation) + (SELECT count(*) FROM region) AS n) SELECT 'a file an object' AS layout, n AS files, n AS objects FROM n UNION ALL SELECT 'packs', 1, n FROM n")
def base_one_file_per_object(s, d):
    """The nation and region rows of the dictionary, written both ways."""
    from evigraph.plans.store import path_for

    f = pack.frames(ingest.dictionary(s, d).filter(F.get_json_object("body", "$.table").isin("nation", "region")))
    store = path_for(s, "pack")
    pack.append(f.select(CAPSULE), store, buckets=1)
    a, b = B.one_file_per_object(f, path_for(s, "objects")), B.laid_out(s.read.parquet(store))
    return a.select(F.lit("a file an object").alias("layout"), "files", "objects").unionByName(b.select(F.lit("packs").alias("layout"), "files", "objects"))


@query("SELECT count(*) AS pairs, count(*) FILTER (a.user_id <> b.user_id) AS cross_scope FROM events a JOIN events b ON a.event_type = b.event_type AND epoch_us(a.ts) < epoch_us(b.ts) AND epoch_us(b.ts) - epoch_us(a.ts) <= 3600000000 WHERE a.event_type IN ('view', 'click', 'purchase')")
def base_unscoped_links(s, d):
    from dataclasses import replace

    return B.unscoped_links(event_tags(s, d), replace(L.R1, window_us=3_600_000_000))


def flagship(s: SparkSession, d: str) -> DataFrame:
    """The minimum slice: star capsules, tags, R3 links capped at both ends, one row per link."""
    return L.derive(item_tags(s, d, L.R3), L.R3, "both").select("link_id", "scope", "src", "dst", "relation", "score", "link_us")
