"""Queries with planted faults, long chains, reopened stores and the paper's regression set: what must be
found, refused or kept is counted by SQL from the tables."""

from __future__ import annotations

from dataclasses import replace

from pyspark.sql import DataFrame, SparkSession, Window
from pyspark.sql import functions as F

from evigraph import oracles as O
from evigraph.functions.canonical import CAPSULE
from evigraph.operators import clearance as CL
from evigraph.operators import links as L
from evigraph.operators import search, status, structure, trust
from evigraph.plans import baselines as B
from evigraph.plans import identity, measures, projection, retrieval
from evigraph.plans.store import appended, passing, path_for, written
from evigraph.sources import exchange, ingest, pack
from evigraph.workloads import _attestations, _classed, _context_inputs, _keys, _migrated, _truth, event_nodes, event_status, event_tags, item_tags, query, user_watermarks

CUT = 1_706_140_800_000_000  # 2024-01-25
_R1_LINKS = O.R1_RANKED + "SELECT scope, src, dst, tag FROM ranked WHERE r1n <= 3 AND r2n <= 3"
_USERS = "(SELECT count(DISTINCT user_id) FROM events)"


def _prepared(s: SparkSession, d: str) -> tuple[projection.Store, DataFrame, DataFrame]:
    return projection.Store(s), written(event_tags(s, d)), written(user_watermarks(s, d))


# packs


@query("""WITH n AS (SELECT (SELECT count(*) FROM customer) + (SELECT count(*) FROM orders) + (SELECT count(*) FROM lineitem) AS n, (SELECT count(*) FROM orders WHERE o_orderkey % 100 = 3) AS lost, (SELECT count(*) FROM customer WHERE c_custkey % 10 = 0) AS changed)
SELECT n - lost AS frames, changed + (SELECT count(*) FROM orders WHERE o_orderkey % 7 = 0 AND o_orderkey % 100 <> 3) AS bad_crc, changed AS bad_id, (SELECT count(*) FROM lineitem WHERE l_orderkey % 100 = 3) AS missing_parents FROM n""")
def verify_damaged(s, d):
    """Bodies changed, checksums changed, frames lost: each is found and told apart."""
    key = F.get_json_object("body", "$.key").cast("long")
    f = pack.frames(ingest.star(s, d)).withColumn("n", key)
    f = f.filter("kind <> 'episode' or n % 100 <> 3")
    f = f.withColumn("body", F.when((F.col("kind") == "subject") & (F.col("n") % 10 == 0), F.concat("body", F.lit(" "))).otherwise(F.col("body")))
    f = f.withColumn("frame_crc", F.when((F.col("kind") == "episode") & (F.col("n") % 7 == 0), F.col("frame_crc") + 1).otherwise(F.col("frame_crc")))
    return pack.verify_full(written(f.drop("n")))


@query("SELECT count(*) FILTER (o_custkey % 20 = 0) AS fallbacks, (SELECT count(*) FROM customer WHERE c_custkey % 20 = 0) AS failed FROM orders")
def ingest_failures_planted(s, d):
    """Subjects that were not stored: they count as failed, their episodes as without their parent."""
    c = written(ingest.subjects(s, d).filter("c_custkey % 20 <> 0").select(CAPSULE).unionByName(ingest.episodes(s, d).select(CAPSULE)))
    n = ingest.read(s, d, "customer").count() + ingest.read(s, d, "orders").count()
    return measures.ingest_failures(n, c, structure.dangling(c))


@query("SELECT (SELECT count(*) FROM orders) AS stored, count(*) FILTER (c_custkey % 20 = 0) AS second_append FROM customer")
def append_again_with_news(s, d):
    """Appending all subjects onto a store that holds all but each twentieth adds those only."""
    c, store = written(ingest.subjects(s, d).select(*CAPSULE, "c_custkey")), path_for(s, "pack")
    pack.append(ingest.episodes(s, d).select(CAPSULE), store, buckets=8)
    stored = s.read.parquet(store).count()
    pack.append(c.filter("c_custkey % 20 <> 0").select(CAPSULE), store, buckets=8)
    more = written(pack.append(c.select(CAPSULE), store, buckets=8))
    return more.agg(F.count("*").alias("second_append")).withColumn("stored", F.lit(stored).cast("long"))


@query("SELECT count(*) AS asked, count(*) AS found FROM orders WHERE o_orderkey % 20 = 0")
def pack_get(s, d):
    """Random access by id through the bucket of the scope."""
    e, store = written(ingest.episodes(s, d)), path_for(s, "pack")
    pack.append(e.select(CAPSULE), store)
    ids = e.filter("o_orderkey % 20 = 0").select("scope_root", "capsule_id")
    return ids.agg(F.count("*").alias("asked")).crossJoin(pack.get(s.read.parquet(store), ids).agg(F.count("*").alias("found")))


# structure and status over long chains

_CHAIN = "c AS (SELECT o_custkey AS scope, o_orderkey AS node, row_number() OVER (PARTITION BY o_custkey ORDER BY o_orderdate, o_orderkey) AS i, count(*) OVER (PARTITION BY o_custkey) AS n FROM orders)"


def _chain(s, d) -> DataFrame:
    """Every customer's orders in time: scope, node, place i of n, the one before and the last."""
    w = Window.partitionBy("o_custkey").orderBy("o_orderdate", "o_orderkey")
    whole = Window.partitionBy("o_custkey")
    o = ingest.read(s, d, "orders")
    c = o.select(F.col("o_custkey").alias("scope"), F.col("o_orderkey").alias("node"), F.unix_micros(F.col("o_orderdate").cast("timestamp")).alias("us"), F.row_number().over(w).cast("long").alias("i"), F.count("*").over(whole).alias("n"), F.lag("o_orderkey").over(w).alias("before"), F.last("o_orderkey").over(w.rowsBetween(Window.unboundedPreceding, Window.unboundedFollowing)).alias("last"))
    return written(c)


@query(f"WITH {_CHAIN} SELECT count(*) FILTER (scope % 50 = 0 AND n > 1) AS cyclic FROM c")
def dag_deep_chain(s, d):
    """Orders as children of the one before; in each fiftieth scope the first is also a child of the last.
    Only those scopes are cyclic, however long the other chains are."""
    c = _chain(s, d)
    edges = c.filter("before is not null").select(F.col("node").alias("child"), F.col("before").alias("parent"))
    back = c.filter("scope % 50 = 0 and i = 1 and n > 1").select(F.col("node").alias("child"), F.col("last").alias("parent"))
    return structure.check_dag(edges.unionByName(back)).agg(F.count("*").alias("cyclic"))


@query(f"WITH {_CHAIN} SELECT scope, n - 1 AS depth FROM c WHERE i = 1")
def closure_to_the_end(s, d):
    c = _chain(s, d)
    edges = c.filter("before is not null").select(F.col("node").alias("child"), F.col("before").alias("parent"))
    seeds = c.filter("i = 1").select(F.col("node").alias("seed"), "scope")
    deep = structure.closure(seeds.select("seed"), edges).groupBy("seed").agg(F.max("distance").cast("long").alias("depth"))
    return seeds.join(deep, "seed").select("scope", "depth")


@query(f"WITH {_CHAIN} SELECT node, n - i AS above, i - 1 AS below FROM c")
def closure_both_ways(s, d):
    """How many orders lie after and before each, by closures up and down and by plain SQL."""
    c = _chain(s, d)
    edges = written(c.filter("before is not null").select(F.col("node").alias("child"), F.col("before").alias("parent")))
    seeds = c.select(F.col("node").alias("seed"))
    count = lambda way, name: structure.closure(seeds, edges, way).groupBy(F.col("seed").alias("node")).agg((F.count("*") - 1).alias(name))
    return count("down", "above").join(count("up", "below"), "node")


@query(f"WITH {_CHAIN} SELECT scope, n - 1 AS depth FROM c WHERE i = 1")
def closure_recursive_sql(s, d):
    """The same depths by a recursive query over the edges."""
    _chain(s, d).createOrReplaceTempView("chain_of_orders")
    return s.sql("""WITH RECURSIVE walk(scope, node, depth) AS (
        SELECT scope, node, CAST(0 AS BIGINT) FROM chain_of_orders WHERE i = 1
        UNION ALL SELECT c.scope, c.node, walk.depth + 1 FROM walk JOIN chain_of_orders c ON c.before = walk.node)
        SELECT scope, max(depth) AS depth FROM (SELECT * FROM walk LIMIT ALL) GROUP BY scope""")


@query(f"""WITH {_CHAIN}, l AS (SELECT scope, node AS last FROM c WHERE i = n)
SELECT node, CASE WHEN i = n THEN 'current' WHEN scope % 2 = 0 THEN 'superseded' WHEN (n - i) % 2 = 1 THEN 'retracted' ELSE 'current' END AS status,
CASE WHEN scope % 2 = 0 THEN last WHEN (n - i) % 2 = 0 THEN node ELSE -1 END AS current FROM c JOIN l USING (scope)""")
def status_long_chain(s, d):
    """Each customer's orders as one chain: in even scopes each amends the one before, in odd ones it
    withdraws it."""
    c = _chain(s, d)
    kind = F.when(F.col("before").isNull(), "signal").when(F.col("scope") % 2 == 0, "amendment").otherwise("retraction")
    nodes = c.select("node", "scope", "us", kind.alias("kind"), F.col("before").alias("target"), F.lit(True).alias("attested"))
    return status.resolve(nodes).select("node", "status", F.coalesce("current", F.lit(-1)).alias("current"))


@query("SELECT CASE WHEN o_orderkey % 50 = 0 AND o_custkey <> 1 THEN 2 ELSE 1 END AS roots, count(*) AS n FROM orders GROUP BY 1 UNION ALL SELECT 3, count(*) FROM lineitem WHERE l_orderkey % 50 = 1 AND l_linenumber = 1 HAVING count(*) > 0")
def multi_root_planted(s, d):
    """Each fiftieth order also hangs under customer 1, and items of some hang under three orders of
    three customers: both are seen to have several roots."""
    o = ingest.read(s, d, "orders")
    c = ingest.read(s, d, "customer").select(F.concat(F.lit("c"), F.col("c_custkey")).alias("capsule_id"), F.array().cast("array<string>").alias("parents"))
    two = F.when((F.col("o_orderkey") % 50 == 0) & (F.col("o_custkey") != 1), F.array(F.concat(F.lit("c"), F.col("o_custkey")), F.lit("c1"))).otherwise(F.array(F.concat(F.lit("c"), F.col("o_custkey"))))
    e = o.select(F.concat(F.lit("o"), F.col("o_orderkey")).alias("capsule_id"), two.alias("parents"))
    extra = s.createDataFrame([(f"x{k}", []) for k in range(2)], "capsule_id string, parents array<string>")
    lone = ingest.read(s, d, "lineitem").filter("l_orderkey % 50 = 1 and l_linenumber = 1").withColumn("n", F.monotonically_increasing_id())
    i = lone.select(F.concat(F.lit("i"), F.col("n")).alias("capsule_id"), F.array(F.concat(F.lit("o"), F.col("l_orderkey")), F.lit("x0"), F.lit("x1")).alias("parents"))
    every = c.unionByName(e).unionByName(extra).unionByName(i).withColumn("scope_root", F.lit(""))
    found = structure.scope_of(every).filter("capsule_id not like 'c%' and capsule_id not like 'x%'")
    return found.groupBy(F.size("roots").alias("roots")).agg(F.count("*").alias("n"))


@query(O.OBS + """, c AS (SELECT event_id AS node, user_id AS scope, coalesce(amended, retracted) AS target FROM obs WHERE amended IS NOT NULL OR retracted IS NOT NULL)
SELECT CASE WHEN node % 7 = 0 THEN 'missing' ELSE 'cross_scope' END AS reason, count(*) AS n FROM c WHERE node % 7 = 0 OR node % 11 = 0 GROUP BY 1""")
def bad_targets_planted(s, d):
    """Corrections moved to another scope, and corrections of what is not stored."""
    e = event_nodes(s, d)
    moved, lost = F.col("target").isNotNull() & (F.col("node") % 11 == 0), F.col("target").isNotNull() & (F.col("node") % 7 == 0)
    e = e.withColumns({"scope": F.when(moved & ~lost, -F.col("node") - 1).otherwise(F.col("scope")), "target": F.when(lost, -F.col("target") - 1).otherwise(F.col("target"))})
    return status.bad_targets(e).filter("node % 7 = 0 or node % 11 = 0").groupBy("reason").agg(F.count("*").alias("n"))


# projection store


@query(f"SELECT 'g2' AS generation, {_USERS} AS scopes")
def store_reopened(s, d):
    """A store opened again goes on where it was: the generation published last is the one seen."""
    store, tags, marks = _prepared(s, d)
    for rule, generation in ((L.R1, "g1"), (L.R2, "g1b")):
        projection.project_scopes(store, tags, marks, [rule], generation)
    again = projection.Store(s, store.root)
    projection.project_scopes(again, tags, marks, [L.R1], "g2")
    return projection.Store(s, store.root).progress(marks)


@query(f"SELECT scope, count(*) AS links FROM ({_R1_LINKS}) GROUP BY 1")
def run_published_twice(s, d):
    """The same run published again, after a cut as well, does not double its links."""
    store, tags, marks = _prepared(s, d)
    run = projection.project_scopes(store, tags, marks, [L.R1], "g1")
    # links of an attempt that never came to its pointer rows
    store._append("links", L.project(tags, [L.R1], run).withColumn("attempt", F.lit("cut")))
    projection.project_scopes(projection.Store(s, store.root), tags, marks, [L.R1], "g1")
    return projection.Store(s, store.root).links().groupBy("scope").agg(F.count("*").alias("links"))


@query(f"SELECT 'live' AS what, count(*) AS n FROM ({_R1_LINKS}) UNION ALL SELECT 'stored', count(*) FROM ({_R1_LINKS})")
def store_compacted(s, d):
    """After a compaction the store holds what readers see and nothing else."""
    store, tags, marks = _prepared(s, d)
    for rule in (L.R2, L.R1):
        projection.project_scopes(store, tags, marks, [rule], "g1")
    new = store.compacted()
    return new.links().agg(F.lit("live").alias("what"), F.count("*").alias("n")).unionByName(new._read("links", projection.LINKS).agg(F.lit("stored").alias("what"), F.count("*").alias("n")))


@query("SELECT 'g2' AS active, CASE WHEN user_id % 3 = 0 THEN 'g2' ELSE 'g1' END AS generation, count(DISTINCT user_id) AS scopes FROM events GROUP BY 2")
def active_generation(s, d):
    """The pointer says where readers are to be, the state where each scope is; a generation without a
    manifest is refused."""
    store, tags, marks = _prepared(s, d)
    projection.project_scopes(store, tags, marks, [L.R1], "g1")
    projection.project_scopes(store, tags, marks.filter("scope % 3 = 0"), [L.R2], "g2")
    store.activate("g1")
    store.activate("g2")
    try:
        store.activate("g3")
        raise AssertionError("a generation without a manifest was taken")
    except ValueError:
        pass
    return store.progress(marks).withColumn("active", F.lit(projection.Store(s, store.root).active()))


@query(f"SELECT count(*) AS n_a, count(*) AS n_b, count(*) AS both, 1000000 AS jaccard_ppm, 2 AS refused FROM ({_R1_LINKS})")
def reproduce_run(s, d):
    """An old run derived again from its manifest gives its links; other facts or missing rules are refused."""
    store, tags, marks = _prepared(s, d)
    run = projection.project_scopes(store, tags, marks, [L.R1], "g1")
    old = written(store.links())
    projection.project_scopes(store, tags, marks, [L.R2], "g2")
    again = projection.reproduce(store, run, tags, [L.R1, L.R2])
    refused = 0
    for facts, rules in ((tags.withColumn("k", F.col("k") + 1), [L.R1]), (tags, [L.R2])):
        try:
            projection.reproduce(store, run, facts, rules)
        except ValueError:
            refused += 1
    return measures.jaccard(old, again, ["link_id"]).withColumn("refused", F.lit(refused))


@query(f"SELECT count(*) AS n_a, count(*) AS n_b, count(*) AS both, 1000000 AS jaccard_ppm, true AS orders_differ FROM ({_R1_LINKS})")
def schedule_invariance(s, d):
    """Two schedules, one by class and one the other way round in pages of another size: the same links."""
    store, tags, marks = _prepared(s, d)
    other = projection.Store(s)
    n = marks.count()
    a = projection.drain(store, tags, marks.withColumn("class", (F.lit(1) + F.col("scope") % 3).cast("int")), [L.R1], "g1", -(-n // 3))
    b = projection.drain(other, tags, marks.withColumn("class", (F.lit(3) - F.col("scope") % 3).cast("int")), [L.R1], "g1", -(-n // 2))
    return measures.jaccard(store.links(), other.links(), ["link_id"]).withColumn("orders_differ", F.lit(a != b))


@query(f"""WITH a AS (SELECT scope, count(*) AS n FROM ({_R1_LINKS}) GROUP BY 1), b AS (SELECT scope, count(*) AS n FROM ({O.R2_RANKED} SELECT scope, src, dst FROM ranked WHERE r1n <= 2 AND r2n <= 2) GROUP BY 1)
SELECT n_regionkey AS institution, CASE WHEN n_regionkey % 2 = 0 THEN 'release-1' ELSE 'release-2' END AS generation, CAST(sum(CASE WHEN n_regionkey % 2 = 0 THEN a.n ELSE b.n END) AS BIGINT) AS links
FROM a LEFT JOIN b USING (scope) JOIN customer ON c_custkey = scope JOIN nation ON n_nationkey = c_nationkey GROUP BY 1, 2""")
def institution_generations(s, d):
    """Each region projects its own scopes by its own release over the shared facts."""
    tags, marks = written(event_tags(s, d)), written(user_watermarks(s, d))
    home = ingest.read(s, d, "customer").join(ingest.read(s, d, "nation"), F.col("c_nationkey") == F.col("n_nationkey")).select(F.col("c_custkey").alias("scope"), "n_regionkey")
    marks = written(marks.join(home, "scope"))
    root, out = path_for(s, "institutions"), None
    for region in range(5):
        store = projection.institution(s, root, str(region))
        rules, generation = ([L.R1], "release-1") if region % 2 == 0 else ([L.R2], "release-2")
        projection.project_scopes(store, tags, marks.filter(F.col("n_regionkey") == region).drop("n_regionkey"), rules, generation)
        one = store.links().join(store.state().select("scope", "generation"), "scope").groupBy("generation").agg(F.count("*").alias("links")).withColumn("institution", F.lit(region))
        out = one if out is None else out.unionByName(one)
    return out


@query("""WITH u AS (SELECT DISTINCT user_id FROM events) SELECT count(*) AS drained, count(*) FILTER (user_id % 4 = 2) AS failed_first, 2 AS attempts_at_most, 0 AS left_over FROM u""")
def drain_with_retry(s, d):
    """Pages that hold a scope of class 3 fail the first time: those scopes wait, are noted, and are tried again."""
    store, tags, marks = _prepared(s, d)
    m = written(marks.withColumn("class", (F.lit(1) + F.col("scope") % 4).cast("int")))
    seen: list[int] = []

    def fail(p: DataFrame) -> str | None:
        bad = p.filter("class = 3").count()
        if bad and len(seen) < m.filter("class = 3").count():
            seen.extend([1] * p.count())
            return "timeout"
        return None

    # one class a page, so that a page fails as a whole
    done = 0
    for k in (1, 2, 3, 4):
        done += sum(n for _, n in projection.drain(store, tags, m.filter(F.col("class") == k), [L.R2], "g2", 1_000_000, fail))
    failures = projection.retry_latest(store.failures().select("scope", "error", F.col("at").alias("at_us")))
    left = projection.backlog(m, store.state(), "g2").agg(F.count("*").alias("left_over"))
    return failures.agg(F.count("*").alias("failed_first"), (F.max("attempts") + 1).cast("int").alias("attempts_at_most")).crossJoin(left).withColumn("drained", F.lit(done).cast("long"))


def _access(policy: str):
    return lambda s, d: projection.access(_classed(s, d).select("scope"), _migrated(s, d).filter("scope % 5 <> 0"), "g2", policy).select("scope", "decision")


for _policy, _late_case, _none_case in (("allow_prior", "prior", "project"), ("project_on_access", "project", "project"), ("deny_high_risk", "deny", "deny")):
    query(f"SELECT c_custkey AS scope, CASE WHEN c_custkey % 5 = 0 THEN '{_none_case}' WHEN c_custkey % 3 = 0 THEN 'current' ELSE '{_late_case}' END AS decision FROM customer", f"access_{_policy}")(_access(_policy))


@query(f"SELECT 1 AS touched, {_USERS} AS total, {_USERS} - 1 AS untouched")
def append_touches_its_scope(s, d):
    """New events of one user: that scope alone is projected again, all others keep their attempt."""
    store, tags, marks = _prepared(s, d)
    projection.project_scopes(store, tags.filter(F.col("us") < CUT), marks.withColumn("watermark", F.lit(0).cast("long")), [L.R1], "g1")
    before = written(store.state().select("scope", F.col("attempt").alias("was")))
    one = marks.filter(F.col("scope") == marks.agg(F.min("scope")).first()[0])
    projection.project_scopes(store, tags, one, [L.R1], "g1")
    j = store.state().join(before, "scope").withColumn("moved", F.col("attempt") != F.col("was"))
    return measures.locality(j.filter("moved").select("scope"), marks).crossJoin(j.filter("not moved").agg(F.count("*").alias("untouched")))


@query("""WITH u AS (SELECT c_custkey FROM customer WHERE c_custkey < 10), o AS (SELECT o_orderkey FROM orders WHERE o_custkey < 10)
SELECT (SELECT count(*) FROM u) + (SELECT count(*) FROM o) + (SELECT count(*) FROM lineitem WHERE l_orderkey IN (SELECT o_orderkey FROM o)) + (SELECT count(*) FROM events WHERE user_id IN (SELECT c_custkey FROM u)) AS objects,
""" + f"(SELECT count(*) FROM ({_R1_LINKS}) WHERE scope < 10 AND scope IN (SELECT c_custkey FROM u)) AS links, 0 AS failures")
def regression_ten(s, d):
    """The paper's regression set: ten subjects with all that belongs to them, one rule, no failures."""
    ten = ingest.subjects(s, d).filter("c_custkey < 10").select("capsule_id", "c_custkey")
    c = written(ingest.star(s, d).unionByName(ingest.signals(s, d).select(CAPSULE)).join(ten.select(F.col("capsule_id").alias("scope_root")), "scope_root", "left_semi"))
    tags = event_tags(s, d).join(ten.select(F.col("c_custkey").alias("scope")), "scope", "left_semi")
    store = projection.Store(s)
    marks = event_nodes(s, d).join(ten.select(F.col("c_custkey").alias("scope")), "scope", "left_semi").groupBy("scope").agg(F.max("us").alias("watermark"))
    projection.project_scopes(store, written(tags), written(marks), [L.R1], "g1")
    counts = c.agg(F.count("*").alias("objects")).crossJoin(store.links().agg(F.count("*").alias("links")))
    return counts.crossJoin(structure.dangling(c).agg(F.count("*").alias("failures")))


@query(f"SELECT f AS factor, f * {_USERS} AS scopes, f * (SELECT count(*) FROM ({_R1_LINKS})) AS links FROM (VALUES (1), (2), (4)) t(f)")
def scale_curve(s, d):
    """Scopes copied 1, 2 and 4 times under new keys: links grow as the scopes do."""
    tags, out = written(event_tags(s, d)), None
    for f in (1, 2, 4):
        many = tags.withColumn("copy", F.explode(F.sequence(F.lit(1), F.lit(f)))).withColumns({"scope": F.col("scope") * 8 + F.col("copy"), "node": F.col("node") * 8 + F.col("copy")}).drop("copy")
        one = L.derive(many, L.R1).agg(F.lit(f).alias("factor"), F.count("*").alias("links"))
        out = one if out is None else out.unionByName(one)
    total = user_watermarks(s, d).count()  # scopes without links of their own count too
    return out.select("factor", (F.col("factor").cast("long") * total).alias("scopes"), "links")


# links


@query(f"SELECT count(*) AS n_a, count(*) AS n_b, count(*) AS both, 1000000 AS jaccard_ppm FROM ({_R1_LINKS})")
def link_stability_sets(s, d):
    """Two builds over other partitions, each counted: the ids agree as sets."""
    a = L.derive(event_tags(s, d), L.R1)
    b = L.derive(event_tags(s, d).repartition(13, "k").sortWithinPartitions(F.desc("node")), L.R1)
    return measures.jaccard(written(a), written(b), ["link_id"])


@query(f"SELECT scope, src, dst, true AS warning FROM ({O.R2_RANKED} SELECT scope, src, dst FROM ranked WHERE r1n <= 2 AND r2n <= 2) UNION ALL SELECT scope, src, dst, false FROM ({_R1_LINKS})")
def project_two_rules(s, d):
    """Several rules over one set of tags: assertions of both stay side by side, each under its rule."""
    warn = replace(L.R2, severity="warning", basis="curated", author="curator")
    both = L.project(event_tags(s, d), [L.R1, warn], "run")
    return both.select("scope", "src", "dst", (F.col("severity") == "warning").alias("warning"))


@query(f"""WITH a AS ({O.R2_RANKED} SELECT scope, src, dst, score FROM ranked WHERE r1n <= 2 AND r2n <= 2), b AS (SELECT scope, src, dst, score FROM ({O.R1_RANKED} SELECT scope, src, dst, score FROM ranked WHERE r1n <= 3 AND r2n <= 3)),
l AS (SELECT *, 1 AS sev FROM a UNION ALL SELECT *, 0 FROM b), e AS (SELECT scope, src, dst, score, sev, unnest([src, dst]) AS node FROM l),
r AS (SELECT *, row_number() OVER (PARTITION BY node ORDER BY sev DESC, score DESC, src, dst) AS r FROM e) SELECT node, src, dst, sev FROM r WHERE r = 1""")
def complete_order(s, d):
    """The first link of every node over two rules: a warning goes before any better score."""
    warn = replace(L.R2, severity="warning", basis="curated", author="curator")
    l = L.ranks(L.project(event_tags(s, d), [L.R1, warn], "run")).withColumn("node", F.explode(F.array("src", "dst")))
    r = l.withColumn("r", F.row_number().over(Window.partitionBy("node").orderBy(*L.order(True)))).filter("r = 1")
    return r.select("node", "src", "dst", F.col("rank_severity").alias("sev"))


@query("SELECT 'R1' AS name, 1 AS revision, true AS applies UNION ALL SELECT 'R1', 2, false UNION ALL SELECT 'R4', 1, true")
def rules_applicable(s, d):
    """Rules as content, and which of them hold at a time: a revision is another capsule."""
    rules = [replace(L.R1, valid_us=(0, CUT + 1)), replace(L.R2, valid_us=(CUT + 1, 1 << 62)), L.R4]
    now = {r.rule_id() for r in L.applicable(rules, CUT)}
    return L.rule_capsules(s, rules).select("name", "revision", F.col("rule_id").isin(*now).alias("applies"))


@query("SELECT 0 AS above_info, 3 * count(*) FILTER (vec_id % 40 = 0) AS rejected, 3 * count(*) FILTER (vec_id % 40 <> 0) AS accepted FROM embeddings WHERE vec_id % 20 = 0")
def proposals_stay_info(s, d):
    """Pairs that vectors propose pass the gate at info; those that some raised to a warning do not."""
    v = ingest.read(s, d, "embeddings")
    pairs = search.vector_topk(v, v.filter("vec_id % 20 = 0"), 3).select(F.col("query_id").alias("src"), F.col("vec_id").alias("dst")).withColumn("evidence_id", F.lit(""))
    raised = L.propose(pairs, "learned").withColumn("severity", F.when(F.col("src") % 40 == 0, "warning").otherwise(F.col("severity")))
    ok, no = L.escalation_gate(raised, s.createDataFrame([], "evidence_id string"))
    return ok.agg(F.count_if(F.col("severity") != "info").alias("above_info"), F.count("*").alias("accepted")).crossJoin(no.agg(F.count("*").alias("rejected")))


@query(O.OBS + """SELECT a.user_id AS scope, a.event_id AS src, b.event_id AS dst, 7 * (100 - abs(a.k - b.k)) + 2 * (100 - (100 * (b.us - a.us)) // 604800000000) + 5 AS score FROM obs a JOIN obs b ON a.user_id = b.user_id AND a.event_type = b.event_type AND (a.us < b.us OR a.us = b.us AND a.event_id < b.event_id)
WHERE a.event_type = 'purchase' AND b.us - a.us BETWEEN 3600000000 AND 604800000000""")
def rule_parameters(s, d):
    """A rule with its own kinds, least gap and weights."""
    rule = replace(L.R1, kinds=("purchase",), min_gap_us=3_600_000_000, weights={"closeness": 7, "recency": 2, "shared": 5})
    tags = event_tags(s, d).withColumn("kind", F.col("code"))
    return L.score(L.candidates(tags, rule), rule).select("scope", "src", "dst", "score")


@query(O.R3 + "SELECT scope, src, dst, 'warning' AS severity, 2 AS paths FROM cand")
def consolidated_paths(s, d):
    """Two rules of two severities over one pair: the higher one is shown, and what each rests on is kept."""
    c = written(L.score(L.candidates(item_tags(s, d, L.R3), L.R3).filter("src_k <> dst_k"), L.R3))
    both = L.identify(c, L.R3).unionByName(L.identify(c, replace(L.R6, severity="warning", basis="curated")))
    return L.consolidate(both).select("scope", "src", "dst", "severity", F.size("paths").cast("long").alias("paths"))


@query("SELECT count(*) AS rebuilt, count(*) FILTER (user_id = (SELECT min(user_id) FROM events)) AS local FROM events WHERE event_type IN ('view', 'click', 'purchase')")
def base_rebuild_contrast(s, d):
    """Tags that a corpus-wide rebuild reads after one subject's append, and those a scope-local one reads."""
    tags, marks = written(event_tags(s, d)), user_watermarks(s, d)
    one = marks.filter(F.col("scope") == marks.agg(F.min("scope")).first()[0])
    return tags.agg(F.count("*").alias("rebuilt")).crossJoin(tags.join(one.select("scope"), "scope", "left_semi").agg(F.count("*").alias("local")))


# clearance and contamination


@query(O.R1_NODES + "SELECT 'removed' AS way, 0 AS leaked UNION ALL SELECT 'unfiltered', count(DISTINCT node) FROM (SELECT unnest([src, dst]) AS node FROM kept) JOIN nodes USING (node) WHERE level > 1")
def leakage_contrast(s, d):
    """Hidden ids that show in links: none once both ends are checked, all of them otherwise."""
    nodes, links = event_nodes(s, d), written(L.derive(event_tags(s, d), L.R1))
    hidden = nodes.filter("level > 1").select("node")
    one = lambda way, df: measures.leakage(df, hidden, ["src", "dst"]).select(F.lit(way).alias("way"), "leaked")
    return one("removed", CL.edges(links, CL.visible(nodes, CL.Caller("nurse")))).unionByName(one("unfiltered", links))


@query(O.CONTEXT + """, raw AS (SELECT k.scope, k.src AS x, k.dst AS y FROM kept k UNION SELECT k.scope, k.dst, k.src FROM kept k),
one AS (SELECT DISTINCT a.anchor, y AS node FROM anchors a JOIN raw ON x = a.node), j AS (SELECT one.*, n.level, st.current FROM one JOIN nodes n ON n.node = one.node JOIN st ON st.node = one.node)
SELECT 'unfiltered' AS way, count(*) AS reached, 0 AS out_of_scope, count(*) FILTER (level > 1) AS hidden, count(*) FILTER (current IS NULL) AS withdrawn, count(*) FILTER (current <> node) AS superseded FROM j
UNION ALL SELECT 'context', (SELECT count(*) FROM got1 WHERE hop = 1), 0, 0, 0, 0""")
def expansion_violations(s, d):
    """Neighbours of the anchors as links alone give them, and as the context does."""
    anchors, nodes, links = _context_inputs(s, d)
    ends = links.select("scope", F.col("src").alias("x"), F.col("dst").alias("y")).unionByName(links.select("scope", F.col("dst").alias("x"), F.col("src").alias("y")))
    raw = anchors.join(ends.withColumnRenamed("x", "node"), ["scope", "node"]).select("anchor", "scope", F.col("y").alias("node"))
    got = retrieval.retrieve_many(anchors, nodes, links, CL.Caller("nurse")).nodes.filter("hop = 1").join(anchors.select("anchor", "scope"), "anchor").select("anchor", "scope", "node")
    one = lambda way, df: measures.expansion_violations(df, nodes, 1).withColumn("way", F.lit(way))
    return one("unfiltered", raw).unionByName(one("context", got))


@query(O.R1_NODES + """, p AS (SELECT min(node) AS p0 FROM nodes), u AS (SELECT scope AS u0 FROM nodes, p WHERE node = p0), pre AS (SELECT event_id AS child, user_id FROM obs)
SELECT 'metadata' AS place, 5 AS violations UNION ALL SELECT 'spine', count(*) FROM obs, u WHERE event_id % 50 = 0 AND user_id <> u0
UNION ALL SELECT 'corrections', count(*) FROM obs, u WHERE coalesce(amended, retracted) IS NOT NULL AND event_id % 4 = 0 AND user_id <> u0
UNION ALL SELECT 'links', count(*) FROM kept, u WHERE src % 30 = 0 AND scope <> u0""")
def contamination_planted(s, d):
    """Parents, corrections and links turned to a node of another scope, and capsules without a root."""
    e = written(event_nodes(s, d))
    p0 = e.agg(F.min("node")).first()[0]
    roots = e.select("node", F.col("scope").alias("root")).unionByName(s.createDataFrame([(-k, None) for k in range(1, 6)], "node long, root long"))
    before = F.lag("node").over(Window.partitionBy("scope").orderBy("us", "node"))
    spine = e.select(F.col("node").alias("child"), F.when(F.col("node") % 50 == 0, F.lit(p0)).otherwise(F.coalesce(before, F.col("node"))).alias("parent"))
    fix = e.filter("target is not null").select("node", F.when(F.col("node") % 4 == 0, F.lit(p0)).otherwise(F.col("target")).alias("target"))
    links = L.derive(event_tags(s, d), L.R1).withColumn("dst", F.when(F.col("src") % 30 == 0, F.lit(p0)).otherwise(F.col("dst")))
    return CL.scan(roots, spine, fix, links)


@query("SELECT count(*) FILTER (l_partkey % 40 = 0) AS quarantined, count(*) FILTER (l_partkey % 40 <> 0) AS accepted FROM (SELECT * FROM lineitem JOIN orders ON l_orderkey = o_orderkey WHERE o_custkey <> 1)")
def ingest_boundary(s, d):
    """Items of which some name an order of customer 1 as a second parent are kept out at ingest."""
    i = ingest.items(s, d).filter("o_custkey <> 1").select("capsule_id", "o_custkey", "l_partkey")
    mine = i.select(F.col("capsule_id").alias("child"), F.col("o_custkey").alias("parent_root"), F.col("o_custkey").alias("expected"))
    other = i.filter("l_partkey % 40 = 0").select(F.col("capsule_id").alias("child"), F.lit(1).cast("long").alias("parent_root"), F.col("o_custkey").alias("expected"))
    bad = written(CL.ingest_check(mine.unionByName(other)).select("child"))
    return bad.agg(F.count("*").alias("quarantined")).crossJoin(i.join(bad.withColumnRenamed("child", "capsule_id"), "capsule_id", "left_anti").agg(F.count("*").alias("accepted")))


@query(O.R1_NODES + "SELECT count(*) FILTER (src % 30 <> 0) AS stored, count(*) FILTER (src % 30 = 0) AS rejected FROM kept")
def storage_boundary(s, d):
    """Before links are written those whose ends and own scope disagree are taken out."""
    links = written(L.derive(event_tags(s, d), L.R1).withColumn("scope", F.when(F.col("src") % 30 == 0, F.col("scope") + 1_000_000).otherwise(F.col("scope"))))
    roots = event_nodes(s, d).select("node", F.col("scope").alias("root"))
    bad = CL.link_check(links, roots).select("link_id")
    return links.join(bad, "link_id", "left_anti").agg(F.count("*").alias("stored")).crossJoin(bad.agg(F.count("*").alias("rejected")))


@query("SELECT 'capsules' AS built_from, false AS foreign_inputs UNION ALL SELECT 'links', true")
def lineage_planted(s, d):
    """Capsules built from source tables pass; some that read projected links are found."""
    store, tags, marks = _prepared(s, d)
    projection.project_scopes(store, tags, marks, [L.R1], "g1")
    sources = ["customer", "orders", "lineitem", "events"]
    tainted = ingest.star(s, d).join(store.links().select(F.col("link_id").alias("capsule_id")), "capsule_id", "left")
    rows = [("capsules", bool(projection.lint_lineage(ingest.star(s, d), sources))), ("links", bool(projection.lint_lineage(tainted, sources)))]
    return s.createDataFrame(rows, "built_from string, foreign_inputs boolean")


@query("""WITH l AS (SELECT doc_id AS node, CASE WHEN toxic = 1 THEN 2 WHEN quality = 0 THEN 1 ELSE 0 END AS level FROM labels)
SELECT r.role, count(*) FILTER (level > r.lv) AS refs_shown FROM l, (VALUES ('auditor', -1), ('clinician', 2)) r(role, lv) GROUP BY 1""")
def audit_refs(s, d):
    """What clearance left out is listed to the auditor and to nobody else."""
    lab = ingest.read(s, d, "labels").select(F.col("doc_id").alias("node"), F.when(F.col("toxic") == 1, 2).when(F.col("quality") == 0, 1).otherwise(0).alias("level"))
    cut = lab.select(F.lit(0).alias("anchor"), "node", F.lit("clearance").alias("cause"))
    one = lambda role: CL.audit_view(cut, CL.Caller(role)).agg(F.count("*").alias("refs_shown")).withColumn("role", F.lit(role))
    return one("auditor").unionByName(one("clinician"))


@query("""WITH c AS (SELECT c_custkey AS node, n_regionkey AS tenant, c_custkey % 3 AS level, c_custkey % 4 <> 0 AS consent FROM customer JOIN nation ON n_nationkey = c_nationkey)
SELECT 'care' AS caller, count(*) FILTER (level <= 1) AS seen, 0 AS logged FROM c UNION ALL SELECT 'research', count(*) FILTER (level <= 0 AND consent), 0 FROM c
UNION ALL SELECT 'emergency', count(*), count(*) FROM c UNION ALL SELECT 'other tenant', count(*) FILTER (level <= 1 AND tenant = 3), 0 FROM c""")
def purpose_and_emergency(s, d):
    """Research needs consent; an emergency sees all and every node seen is logged; a tenant sees its own."""
    c = ingest.read(s, d, "customer").join(ingest.read(s, d, "nation"), F.col("c_nationkey") == F.col("n_nationkey"))
    c = c.select(F.col("c_custkey").alias("node"), F.col("n_regionkey").alias("tenant"), (F.col("c_custkey") % 3).cast("int").alias("level"), (F.col("c_custkey") % 4 != 0).alias("consent"))
    callers = {"care": CL.Caller("nurse"), "research": CL.Caller("researcher", purpose="research"), "emergency": CL.Caller("nurse", emergency=True), "other tenant": CL.Caller("nurse", tenant=3)}
    out = None
    for name, caller in callers.items():
        seen = CL.permitted(c, caller)
        one = seen.agg(F.count("*").alias("seen")).crossJoin(CL.emergency_log(caller, seen).agg(F.count("*").alias("logged"))).withColumn("caller", F.lit(name))
        out = one if out is None else out.unionByName(one)
    return out


@query(O.R1_NODES + """SELECT role, (SELECT count(*) FROM nodes WHERE level <= lv) AS nodes, (SELECT count(*) FROM kept JOIN nodes a ON a.node = src JOIN nodes b ON b.node = dst WHERE a.level <= lv AND b.level <= lv) AS links FROM (VALUES ('researcher', 0), ('nurse', 1), ('clinician', 2), ('stranger', -1)) r(role, lv)""")
def role_views(s, d):
    """The same graph as four roles see it; an unknown role sees nothing."""
    nodes, links = written(event_nodes(s, d)), written(L.derive(event_tags(s, d), L.R1))
    out = None
    for role in ("researcher", "nurse", "clinician", "stranger"):
        seen = CL.visible(nodes, CL.Caller(role))
        one = seen.agg(F.count("*").alias("nodes")).crossJoin(CL.edges(links, seen).agg(F.count("*").alias("links"))).withColumn("role", F.lit(role))
        out = one if out is None else out.unionByName(one)
    return out


@query(O.STATUS + "SELECT event_type, count(*) AS events, count(DISTINCT user_id) AS subjects FROM st JOIN obs ON event_id = node WHERE status = 'current' AND k < 70 GROUP BY 1 HAVING count(DISTINCT user_id) >= 5")
def research_view(s, d):
    """Counts over current, open records without any scope or id, and none over fewer than five subjects."""
    e = event_nodes(s, d).filter("level = 0")
    cur = event_status(s, d).filter("status = 'current'").select("node")
    g = e.join(cur, "node", "left_semi").groupBy("event_type").agg(F.count("*").alias("events"), F.count_distinct("scope").alias("subjects"))
    return g.filter("subjects >= 5")


# retrieval


@query(O.CONTEXT + "SELECT anchor, count(*) AS expected, 0 AS missing, 0 AS violations, 'whole' AS answer FROM (SELECT anchor, node FROM got1 UNION SELECT anchor, node FROM beyond1) GROUP BY 1 UNION ALL SELECT a.anchor, (SELECT count(*) FROM (SELECT anchor, node FROM got1 UNION SELECT anchor, node FROM beyond1) x WHERE x.anchor = a.anchor), (SELECT count(*) FROM got1 g WHERE g.anchor = a.anchor AND hop = 1), 0, 'cut short' FROM anchors a")
def completeness_planted(s, d):
    """An answer without its first hop is seen to be short by exactly that, the whole one by nothing."""
    inputs, limits, caller = tuple(_context_inputs(s, d)), retrieval.Limits(), CL.Caller("nurse")
    r = retrieval.retrieve_many(*inputs, caller, limits)
    short = retrieval.ContextResponse(r.nodes.filter("hop = 0"), r.truncated, r.report)
    one = lambda name, x: retrieval.completeness(x, *inputs, caller, limits).withColumn("answer", F.lit(name))
    return one("whole", r).unionByName(one("cut short", short))


_AMENDED = O.R1_STATUS + O._NODES + """, ok AS (SELECT n.node, n.scope, n.us, st.current FROM nodes n JOIN st ON st.node = n.node WHERE level <= 1 AND current IS NOT NULL),
seen AS (SELECT * FROM ok WHERE current = node), anchors AS (SELECT scope AS anchor, max(node) FILTER (node = current) AS node FROM ok GROUP BY 1),
e AS (SELECT DISTINCT a.current AS x, b.current AS y FROM kept k JOIN ok a ON a.node = k.src JOIN ok b ON b.node = k.dst WHERE a.current <> b.current AND a.current IN (SELECT node FROM seen) AND b.current IN (SELECT node FROM seen)),
w AS (SELECT x, y FROM e UNION SELECT y, x FROM e) """


@query(_AMENDED + "SELECT anchor, node, 0 AS hop FROM anchors WHERE node IS NOT NULL UNION SELECT DISTINCT anchor, y, 1 FROM anchors JOIN w ON x = node")
def context_redirected(s, d):
    """Links of an amended record lead to its current version, in the context of the latest one."""
    e = event_nodes(s, d)
    nodes = written(e.join(status.resolve(e).select("node", "current"), "node").select("node", "scope", "level", "current", "tokens"))
    links = written(L.ranks(L.derive(event_tags(s, d), L.R1)))
    anchors = nodes.filter("level <= 1 and node = current").groupBy("scope").agg(F.max("node").alias("node")).select(F.col("scope").alias("anchor"), "scope", "node")
    r = retrieval.retrieve_many(anchors, nodes, links, CL.Caller("nurse"), retrieval.Limits(per_node=512, total=512))
    return r.nodes.select("anchor", "node", "hop")


def _spine(s, d, part: tuple[int, int] | None = None) -> tuple[DataFrame, DataFrame]:
    """Subjects, orders and items as nodes with levels, and their parent edges, or those of a part of the subjects:
    urgent orders are for clinicians, returned items for nurses. An id is written once, with its parent."""
    c = ingest.owned(ingest.read(s, d, "customer"), "c_custkey", part).select(F.concat(F.lit("c"), F.col("c_custkey")).alias("node"), F.col("c_custkey").alias("scope"), F.lit(0).alias("level"), F.lit(None).cast("string").alias("parent"))
    o = ingest.owned(ingest.read(s, d, "orders"), "o_custkey", part).select(F.concat(F.lit("o"), F.col("o_orderkey")).alias("node"), F.col("o_custkey").alias("scope"), F.when(F.col("o_orderpriority") == "1-URGENT", 2).otherwise(0).alias("level"), F.concat(F.lit("c"), F.col("o_custkey")).alias("parent"))
    i = ingest.items(s, d, part=part).select(F.col("capsule_id").alias("node"), F.col("o_custkey").alias("scope"), F.when(F.col("l_returnflag") == "R", 1).otherwise(0).alias("level"), F.concat(F.lit("o"), F.col("l_orderkey")).alias("parent"))
    every = written(c.unionByName(o).unionByName(i), "zstd")
    nodes = every.drop("parent").withColumns({"current": F.col("node"), "tokens": F.lit(1).cast("long")})
    return nodes, every.filter("parent is not null").select(F.col("node").alias("child"), "parent")


_NO_LINKS = "scope long, src string, dst string, rank_severity int, score long, rule_id string"


@query("""WITH o AS (SELECT * FROM orders WHERE o_orderpriority <> '1-URGENT') SELECT c_custkey AS anchor, 1 + (SELECT count(*) FROM o WHERE o_custkey = c_custkey) + (SELECT count(*) FROM lineitem JOIN o ON l_orderkey = o_orderkey WHERE o_custkey = c_custkey AND l_returnflag <> 'R') AS n_nodes, true AS complete FROM customer""")
def expand_hidden_block(s, d):
    """From each subject two levels down: a hidden order hides its items, though these are open. As a context
    stays in its scope, one part of the subjects is asked after the other."""
    out = path_for(s, "report")
    for part in ingest.parts(s, d, "customer", "orders", "lineitem"):
        with passing(s):
            nodes, spine = _spine(s, d, part)
            anchors = nodes.filter("node like 'c%' and length(node) < 20").select(F.col("scope").alias("anchor"), "scope", "node")
            r = retrieval.retrieve_many(anchors, nodes, s.createDataFrame([], _NO_LINKS), CL.Caller("researcher"), retrieval.Limits(down=2), spine=spine)
            report = r.report.select("anchor", "n_nodes", "complete")
            appended(report, out)
    return s.read.schema(report.schema).parquet(out)


@query("""WITH o AS (SELECT *, row_number() OVER (PARTITION BY o_custkey ORDER BY o_orderdate DESC, o_orderkey DESC) AS r FROM orders), a AS (SELECT * FROM o WHERE r = 1),
v AS (SELECT l_orderkey, count(*) AS n FROM lineitem WHERE l_returnflag <> 'R' GROUP BY 1)
SELECT o_custkey AS anchor, CASE WHEN o_orderpriority = '1-URGENT' THEN 0 ELSE 2 + coalesce(n, 0) END AS n_nodes,
0 AS n_policy FROM a LEFT JOIN v ON l_orderkey = o_orderkey""")
def context_with_spine(s, d):
    """Each customer's latest order with its container and its contents; a hidden anchor gives nothing."""
    nodes, spine = _spine(s, d)
    w = Window.partitionBy("o_custkey").orderBy(F.desc("o_orderdate"), F.desc("o_orderkey"))
    a = ingest.read(s, d, "orders").withColumn("r", F.row_number().over(w)).filter("r = 1").select(F.col("o_custkey").alias("anchor"), F.col("o_custkey").alias("scope"), F.concat(F.lit("o"), F.col("o_orderkey")).alias("node"))
    r = retrieval.retrieve_many(a, nodes, s.createDataFrame([], _NO_LINKS), CL.Caller("researcher"), retrieval.Limits(up=1, down=1), spine=spine)
    return r.report.select("anchor", "n_nodes", "n_policy")


@query("WITH u AS (SELECT DISTINCT user_id FROM events) SELECT user_id AS anchor, 'g1' AS generation, user_id % 5 <> 0 AS caught_up, false AS at_target FROM u WHERE user_id % 3 <> 0 UNION ALL SELECT user_id, 'g2', true, true FROM u WHERE user_id % 3 = 0")
def context_currency(s, d):
    """What each answer says of the projection it stands on: generation, whether it has caught up with
    what is stored, and whether it is the generation readers are pointed at."""
    store, tags, marks = _prepared(s, d)
    late = written(marks.withColumn("watermark", F.when(F.col("scope") % 5 == 0, F.col("watermark") - 1).otherwise(F.col("watermark"))))
    projection.project_scopes(store, tags, late, [L.R1], "g1")
    projection.project_scopes(store, tags, marks.filter("scope % 3 = 0"), [L.R2], "g2")
    store.activate("g2")
    anchors = marks.select(F.col("scope").alias("anchor"), "scope")
    return retrieval.currency(anchors, store.state(), marks, store.active()).drop("run_id")


@query(O.CONTEXT_AS_OF + "SELECT anchor, node, hop FROM got1")
def replay_context(s, d):
    """A context as it stood: facts up to a time, the links of the run named by its manifest, the policy then."""
    e = event_nodes(s, d).filter(F.col("us") <= O.AS_OF)
    tags = written(event_tags(s, d).filter(F.col("us") <= O.AS_OF))
    store = projection.Store(s)
    run = projection.project_scopes(store, tags, written(e.groupBy("scope").agg(F.max("us").alias("watermark"))), [L.R1], "g1")
    now = written(event_tags(s, d))
    projection.project_scopes(store, now, written(user_watermarks(s, d)), [L.R2], "g2")  # what came later
    links = L.ranks(projection.reproduce(store, run, now.filter(F.col("us") <= O.AS_OF), [L.R1, L.R2]))
    st = status.resolve(event_nodes(s, d), as_of=O.AS_OF)
    nodes = written(e.filter("kind = 'signal'").join(st.select("node", "current"), "node").select("node", "scope", "level", "current", "tokens", "us"))
    good = retrieval.live(nodes.filter("level <= 1"))
    anchors = good.groupBy("scope").agg(F.max_by("node", F.struct("us", "node")).alias("node")).select(F.col("scope").alias("anchor"), "scope", "node")
    return retrieval.retrieve_many(anchors, nodes, links, CL.Caller("nurse")).nodes.select("anchor", "node", "hop")


@query("SELECT event_id AS node FROM events WHERE event_type IN ('view', 'click', 'purchase') AND epoch_us(ts) < 1706140800000000 AND event_id % 20 = 0")
def resolve_anchor(s, d):
    """Anchors by id, time and kind at once."""
    e = event_nodes(s, d)
    return retrieval.resolve(e, ids=e.filter("node % 20 = 0"), until=CUT, kinds=("signal",)).select("node")


@query(O.CONTAINS + "SELECT count(*) AS truth, count(*) FILTER (doc_id NOT IN (SELECT doc_id FROM labels WHERE toxic = 1 OR quality = 0)) AS supported, CASE WHEN count(*) = 0 THEN 0 ELSE (count(*) FILTER (doc_id NOT IN (SELECT doc_id FROM labels WHERE toxic = 1 OR quality = 0))) * 1000000 // count(*) END AS ppm FROM truth")
def support_proxy(s, d):
    """Ground-truth passages that stand in documents one may use."""
    bad = ingest.read(s, d, "labels").filter("toxic = 1 or quality = 0").select("doc_id")
    return measures.support(written(_truth(s, d)), ingest.read(s, d, "documents").select("doc_id").join(bad, "doc_id", "left_anti"))


# trust, exchange, identity


_POLICY_OF = "WITH p AS (SELECT unnest(['clinical_origin', 'exchange_import', 'knowledge_release']) AS purpose), a AS (SELECT n_nationkey AS o, n_regionkey AS tenant, purpose FROM nation, p) "


@query(_POLICY_OF + """, q AS (SELECT unnest(['clinical_origin', 'exchange_import', 'knowledge_release']) AS asked)
SELECT asked, purpose AS attested, count(*) FILTER (asked = purpose AND tenant = 1 AND o % 5 NOT IN (2, 3) AND (o % 5 <> 1 OR purpose = 'clinical_origin') AND NOT (o % 5 = 4 AND purpose = 'knowledge_release')) AS counted FROM q, a GROUP BY 1, 2""")
def purpose_interchange(s, d):
    """Attestations of one purpose offered for another never count, whatever they attest."""
    keys = _keys(s, d)
    v = written(trust.verify(_attestations(s, d, keys), trust.key_table(s, keys), 1))
    out = None
    for asked in trust.PURPOSES:
        counted = (F.col("verdict") == "valid") & (F.col("purpose") == asked)
        one = v.groupBy(F.lit(asked).alias("asked"), F.col("purpose").alias("attested")).agg(F.count_if(counted).alias("counted"))
        out = one if out is None else out.unionByName(one)
    return out


@query("SELECT n_nationkey AS organization, CASE WHEN n_nationkey % 2 = 0 THEN 'organization' ELSE 'unknown_key' END AS verdict, 3 AS n FROM nation")
def unknown_key(s, d):
    """Attestations under keys that the policy does not name, or names for another organization."""
    keys = _keys(s, d)
    a = _attestations(s, d, keys)
    known = trust.key_table(s, keys).withColumn("key_org", F.when(F.col("key_org") % 2 == 0, F.col("key_org") + 100).otherwise(F.col("key_org"))).filter("key_org >= 100")
    return trust.policy_verdict(a, known, 1).groupBy("organization", "verdict").agg(F.count("*").alias("n"))


@query("""WITH n AS (SELECT n_nationkey AS o FROM nation WHERE n_regionkey = 1 AND n_nationkey % 5 IN (0, 3)), asked AS (SELECT unnest([50, 2000]) AS at_us), rules AS (SELECT unnest([0, 1, 2]) AS r)
SELECT at_us, r, count(o) >= 1 AS active FROM asked CROSS JOIN rules LEFT JOIN n ON o % 3 = r AND (o % 5 = 0 OR at_us < 100) GROUP BY 1, 2""")
def startup_fails_closed(s, d):
    """Releases approved under keys that were revoked since are inactive at the next start."""
    keys = [replace(k, revoked_us=1500 if k.organization % 5 == 3 else None, valid_to=1 << 62) for k in _keys(s, d) if k.organization % 5 in (0, 3)]
    bodies = {f"rule{r}": f"body of rule {r}" for r in range(3)}
    import hashlib

    ids = {k: hashlib.sha256(v.encode()).hexdigest() for k, v in bodies.items()}
    rows = [trust.attest(ids[f"rule{k.organization % 3}"], "knowledge_release", k, bytes([k.organization]) * 32, "a", 1000) for k in keys]
    a, table = s.createDataFrame(rows, trust.ATTESTATION), trust.key_table(s, keys)
    rules = s.createDataFrame([(r, ids[f"rule{r}"], bodies[f"rule{r}"]) for r in range(3)], "r int, rule_id string, body string")
    out = None
    for at, asked in ((50, 1200), (2000, 2000)):
        one = trust.startup(rules.select("rule_id", "body"), a, table, 1, 1, asked).join(rules.select("r", "rule_id"), "rule_id").select(F.lit(at).alias("at_us"), "r", "active")
        out = one if out is None else out.unionByName(one)
    return out


@query("SELECT count(*) AS pages, count(DISTINCT (regexp_extract(url, '://([^/?#]*)', 1), regexp_extract(url, '://[^/]*/([a-z]+)/', 1), regexp_extract(url, '://[^/]*/[a-z]*/?(\\d+)', 1), regexp_extract(url, '[?&]page=(\\d+)', 1), sha256(html))) AS identities FROM pages")
def source_identity(s, d):
    keyed = exchange.identity_key(exchange.source_key(ingest.read(s, d, "pages")), "t1", "o1", "1")
    return keyed.agg(F.count("*").alias("pages"), F.count_distinct("identity").alias("identities"))


@query("SELECT concat('rule', o % 3) AS subject, concat('actor', j) AS author, o AS signer FROM (SELECT n_nationkey AS o FROM nation), (SELECT unnest([0, 1, 2]) AS j)")
def author_and_signer(s, d):
    return trust.author_and_signer(_attestations(s, d, _keys(s, d)))


@query("SELECT n % 3 AS need, count(*) AS n, count(*) FILTER (have >= need) AS approved FROM (SELECT n_nationkey AS n, n_nationkey % 3 AS need, CAST(n_regionkey = 1 AND n_nationkey % 5 IN (0, 1, 4) AS INT) + 0 AS have FROM nation) GROUP BY 1")
def quorum_short(s, d):
    """Each nation's own statement needs 0, 1 or 2 approvals of the origin; with one signer 2 is never met."""
    keys = _keys(s, d)
    rows = [trust.attest(f"own{k.organization}", "clinical_origin", k, bytes([k.organization]) * 32, "a", 1000) for k in keys]
    v = trust.verify(s.createDataFrame(rows, trust.ATTESTATION), trust.key_table(s, keys), 1)
    have = trust.approved(v, "clinical_origin", 1).select("subject", "approvals")
    every = s.createDataFrame([(f"own{k.organization}", k.organization % 3) for k in keys], "subject string, need int").join(have, "subject", "left")
    return every.groupBy("need").agg(F.count("*").alias("n"), F.count_if(F.coalesce("approvals", F.lit(0)) >= F.col("need")).alias("approved"))


@query("WITH n AS (SELECT count(*) AS n FROM pages) SELECT 'same version' AS way, n AS snapshots, 0 AS remapped FROM n UNION ALL SELECT 'new version', n, n FROM n")
def remap_contrast(s, d):
    """A new mapping version gives new mapped ids, the same version the same ones."""
    snap, _ = ingest.snapshots(s, d)
    out = None
    for way, version in (("same version", "1"), ("new version", "2")):
        a, b = exchange.remap(snap, "1"), exchange.remap(snap, version)
        one = a.join(b.select("capsule_id", F.col("mapped_id").alias("m2")), "capsule_id").agg(F.count("*").alias("snapshots"), F.count_if(F.col("mapped_id") != F.col("m2")).alias("remapped")).withColumn("way", F.lit(way))
        out = one if out is None else out.unionByName(one)
    return out


@query("SELECT count(*) AS landed, count(*) AS once, 3 AS checkpoint, 2 AS runs FROM pages")
def sync_resumed(s, d):
    """A sync that fails in its third page, opened again from its checkpoint: every page lands once."""
    p, out, marks = ingest.read(s, d, "pages"), path_for(s, "sync"), path_for(s, "checkpoint")
    pages = [p.filter(F.col("page_id") % 4 == k).withColumn("part", F.lit(k)) for k in range(4)]
    runs = 0
    for broken in (2, None):
        runs += 1
        since = exchange.checkpoint_of(s, marks)

        def land(x: DataFrame, broken=broken) -> None:
            k = x.select("part").first()["part"]
            if k == broken:
                raise ConnectionError("the server went away")
            x.write.mode("overwrite").parquet(f"{out}/part={k}")

        try:
            exchange.sync(pages, land, lambda k: exchange.mark(s, marks, k), since)
        except ConnectionError:
            continue
    got = s.read.parquet(out)
    return got.agg(F.count("*").alias("landed"), F.count_distinct("page_id").alias("once")).withColumns({"checkpoint": F.lit(exchange.checkpoint_of(s, marks)), "runs": F.lit(runs)})


@query("SELECT n_nationkey AS organization, 1 AS clinical_origin, 2 AS exchange_import, 0 AS merged FROM nation")
def import_provenance(s, d):
    """Origin and importer attestations of a mapped capsule stay apart."""
    keys = _keys(s, d)
    mapped = ingest.read(s, d, "nation").select(F.concat(F.lit("m"), F.col("n_nationkey")).alias("capsule_id"), F.col("n_nationkey").alias("organization"))
    a = mapped.select(F.col("capsule_id").alias("subject"), F.lit("clinical_origin").alias("purpose")).unionByName(mapped.select(F.col("capsule_id").alias("subject"), F.explode(F.array(F.lit("exchange_import"), F.lit("exchange_import"))).alias("purpose")))
    assert len(keys) == mapped.count()
    return exchange.provenance(mapped, a).select("organization", "clinical_origin", "exchange_import", F.lit(0).alias("merged"))


_OWNERS = "WITH n AS (SELECT count(*) AS n FROM customer), o AS (SELECT DISTINCT sha256(text) AS content_id, doc_id % n AS owner FROM documents, n WHERE text IS NOT NULL), g AS (SELECT content_id, owner, lead(owner) OVER (PARTITION BY content_id ORDER BY owner) AS nxt FROM o), pair AS (SELECT DISTINCT owner AS a, nxt AS b FROM g WHERE nxt IS NOT NULL) "


@query(_OWNERS + "SELECT CASE WHEN (a + b) % 4 = 3 THEN 'retracted' WHEN (a + b) % 4 = 2 THEN 'candidate' ELSE 'approved' END AS state, count(*) AS n FROM pair GROUP BY 1")
def identity_states(s, d):
    """Pairs go from candidate to adjudicated to retracted; only a signed adjudication links them."""
    n = ingest.read(s, d, "customer").count()
    owners = ingest.read(s, d, "documents").filter("text is not null").select(F.sha2("text", 256).alias("content_id"), (F.col("doc_id") % n).alias("owner"))
    c = written(identity.candidates(owners))
    ok = identity.adjudicate(c.filter("(a + b) % 4 <> 2"), "steward", 1)
    gone = identity.retract(c.filter("(a + b) % 4 = 3"), "steward", 2)
    return identity.states(c, ok.unionByName(gone)).groupBy("state").agg(F.count("*").alias("n"))


# streams


@query(f"SELECT scope, count(*) AS links, 3 AS batches FROM ({_R1_LINKS}) GROUP BY 1")
def stream_projects_links(s, d):
    """Events that come in three micro-batches: each lands under its number, and the scopes it touches are
    projected again from all that has landed. In the end the links are those of one run over all."""
    from evigraph.streaming import flows

    inbox, home, store = path_for(s, "inbox"), path_for(s, "landed"), projection.Store(s)
    e = ingest.read(s, d, "events")
    for k in range(3):
        e.filter(F.pmod(F.xxhash64("event_id"), F.lit(3)) == k).coalesce(1).write.parquet(f"{inbox}/events{k}.parquet")

    def on_batch(batch: DataFrame, n: int) -> None:
        batch.drop("at").write.mode("overwrite").parquet(f"{home}/batch={n}")  # a batch that is run again replaces itself
        seen = s.read.parquet(home).withColumn("us", F.unix_micros(F.col("ts").cast("timestamp")))
        touched = written(seen.join(batch.select("user_id").distinct(), "user_id", "left_semi"))
        marks = written(touched.groupBy(F.col("user_id").alias("scope")).agg(F.max("us").alias("watermark")))
        own = touched.filter(F.col("event_type").isin("view", "click", "purchase"))
        tags = own.select(F.col("event_id").alias("node"), F.col("user_id").alias("scope"), "us", F.get_json_object("props", "$.k").cast("int").alias("k"), F.lit("etype").alias("ns"), F.col("event_type").alias("code"))
        projection.project_scopes(store, written(tags), marks, [L.R1], "g1")

    batches = flows.landed(flows.events(s, inbox, files=1), on_batch)
    return store.links().groupBy("scope").agg(F.count("*").alias("links")).withColumn("batches", F.lit(batches))
