"""The evidence graph against hand-written answers, plain Python and its own invariants."""

from __future__ import annotations

from functools import reduce

import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from evigraph import scenarios, workloads
from evigraph.functions.canonical import CAPSULE, canonical_text, rehash
from evigraph.operators import clearance, links, status, structure, trust
from evigraph.plans import baselines, measures, projection, retrieval, store
from evigraph.sources import ingest, pack
from evigraph.workloads import event_tags, item_tags, lines_meeting

NODE = "node long, scope long, us long, kind string, target long, attested boolean"


def _status(spark, rows, **kw):
    return {r["node"]: (r["status"], r["current"]) for r in status.resolve(spark.createDataFrame(rows, NODE), **kw).collect()}


def test_status_truth_table(spark):
    s = _status(spark, [
        (1, 1, 1, "signal", None, False), (2, 1, 2, "signal", None, False), (3, 1, 3, "retraction", 2, False), (4, 1, 4, "signal", None, False), (5, 1, 5, "amendment", 4, False),
        (6, 1, 6, "signal", None, False), (7, 1, 7, "amendment", 6, True), (8, 1, 8, "signal", None, False), (9, 1, 9, "amendment", 8, True), (10, 1, 10, "retraction", 8, False),
        (11, 1, 11, "signal", None, False), (12, 1, 12, "amendment", 11, True), (13, 1, 13, "amendment", 11, True), (14, 1, 14, "signal", None, False), (15, 1, 15, "amendment", 14, True), (16, 1, 15, "amendment", 14, True),
        (17, 1, 17, "signal", None, False), (18, 1, 18, "amendment", 17, True), (19, 1, 19, "retraction", 18, False), (20, 2, 20, "amendment", 1, True),
    ])
    assert s[1] == ("current", 1) and s[2] == ("retracted", None) and s[4] == ("current", 4) and s[5][0] == "pending_amendment"
    assert s[6] == ("superseded", 7) and s[8][0] == "retracted" and s[11] == ("superseded", 13) and s[14] == ("superseded", 16)
    assert s[17] == ("current", 17) and s[18][0] == "retracted"


def test_retraction_of_retraction_and_chain(spark):
    s = _status(spark, [(1, 1, 1, "signal", None, False), (2, 1, 2, "retraction", 1, False), (3, 1, 3, "retraction", 2, False), (4, 1, 4, "signal", None, False), (5, 1, 5, "amendment", 4, True), (6, 1, 6, "amendment", 5, True)])
    assert s[1] == ("current", 1) and s[2][0] == "retracted" and s[4] == ("superseded", 6)


def test_long_chains_end(spark):
    rows = [(1, 1, 1, "signal", None, False)] + [(k, 1, k, "retraction", k - 1, False) for k in range(2, 8)]  # six retractions in chain
    rows += [(11, 1, 11, "signal", None, False)] + [(k, 1, k, "amendment", k - 1, True) for k in range(12, 19)]
    s = _status(spark, rows)
    assert [s[k][0] for k in range(1, 8)] == ["current", "retracted", "current", "retracted", "current", "retracted", "current"]
    assert all(s[k] == ("superseded", 18) for k in range(11, 18)) and s[18] == ("current", 18)


def test_greedy_rounds_and_communities_run_to_the_end(spark):
    # scores fall along a path, so a round takes one pair only
    chain = spark.createDataFrame([(1, k, k + 1, 1000 - k) for k in range(14)], "scope long, src long, dst long, score long")
    assert {(r["src"], r["dst"]) for r in links.greedy_rounds(chain, 1).collect()} == {(k, k + 1) for k in range(0, 14, 2)}
    path = [(d, f"e{k + i:02d}") for k in range(20) for d in (2 * k, 2 * k + 1) for i in (0, 1)]
    got = baselines.community_graph(spark.createDataFrame(path, "doc_id long, entity string")).collect()
    assert len(got) == 21 and {r["community"] for r in got} == {"e00"}


def test_bad_targets(spark):
    df = spark.createDataFrame([(1, 1, 1, "signal", None, False), (2, 2, 2, "retraction", 1, False), (3, 1, 3, "retraction", 99, False)], NODE)
    assert {(r["node"], r["reason"]) for r in status.bad_targets(df).collect()} == {(2, "cross_scope"), (3, "missing")}


def test_same_content_same_id_and_tamper(spark, sf):
    a, b = ingest.subjects(spark, sf), ingest.subjects(spark, sf).repartition(3)
    assert measures.jaccard(a, b, ["capsule_id"]).first()["jaccard_ppm"] == 1_000_000
    for column, value in (("body", F.concat("body", F.lit(" "))), ("clinical_us", F.col("clinical_us") + 1), ("parents", F.array(F.lit("x")))):
        t = a.withColumn(column, value)
        assert t.filter(rehash(t) == F.col("capsule_id")).count() == 0


def test_canonical_text():
    assert canonical_text('{"b": 1, "a": [1, {"z": "\\u00e9", "y": null}]}') == '{"a":[1,{"y":null,"z":"é"}],"b":1}'


def test_pack_append_verify_recover(spark, sf, tmp_path):
    c = ingest.subjects(spark, sf).select(CAPSULE)
    store = str(tmp_path / "pack")
    n = c.count()
    pack.append(c, store, buckets=4)
    assert pack.append(c, store, buckets=4).count() == 0
    p = spark.read.parquet(store)
    assert tuple(pack.verify_full(p).first()) == (n, 0, 0, 0)
    assert pack.verify(p.withColumn("body", F.when(F.col("body").contains('"key":3,'), F.lit("{}")).otherwise(F.col("body")))).count() == 1
    f = pack.frames(ingest.star(spark, sf))
    whole = f.groupBy("scope_root").agg(F.max("pack_seq").alias("m"))
    assert whole.filter("m >= 5").count() and pack.recover(f.filter("pack_seq <> 3")).agg(F.max("pack_seq")).first()[0] == 2


def test_greedy_equals_rounds_and_plain_scan(spark, sf):
    s = links.score(links.candidates(event_tags(spark, sf), links.R1), links.R1).select("scope", "src", "dst", "score")
    rows = sorted(s.collect(), key=lambda r: (r["scope"], -r["score"], r["src"], r["dst"]))
    used, want = {}, set()
    for r in rows:
        a, b = (r["scope"], r["src"]), (r["scope"], r["dst"])
        if used.get(a, 0) < 3 and used.get(b, 0) < 3:
            want.add((r["src"], r["dst"]))
            used[a], used[b] = used.get(a, 0) + 1, used.get(b, 0) + 1
    assert {(r["src"], r["dst"]) for r in links.greedy(s, 3).collect()} == want and len(want) == 773
    assert {(r["src"], r["dst"]) for r in links.greedy_rounds(s, 3).collect()} == want
    sizes = {m: links.cap(s, 3, m).count() for m in ("source", "both", "either")}
    assert sizes == {"source": 835, "both": 653, "either": 1038}
    both = {(r["src"], r["dst"]) for r in links.cap(s, 3, "both").collect()}
    assert both <= want and both <= {(r["src"], r["dst"]) for r in links.cap(s, 3, "either").collect()}


def test_link_ids_do_not_depend_on_partitions(spark, sf):
    got = measures.link_stability(lambda: links.derive(event_tags(spark, sf), links.R1), [{"spark.sql.shuffle.partitions": n} for n in ("1", "7")])
    assert len(set(got)) == 1
    c = links.score(links.candidates(event_tags(spark, sf), links.R1), links.R1)
    j = measures.jaccard(baselines.unordered_cap(c, 3, 1), baselines.unordered_cap(c, 3, 2), ["src", "dst"]).first()
    assert j["jaccard_ppm"] < 1_000_000 and abs(j["n_a"] - j["n_b"]) < 0.1 * j["n_a"]


def test_incident_only_is_wrong_under_caps(spark, sf):
    t = event_tags(spark, sf)
    e, p = baselines.incident_only(t, t.filter("us >= 1706140800000000").select("node"), links.R1, "greedy")
    k = ["src", "dst"]
    assert e.count() == 773 and e.join(p, k, "left_anti").count() > 0 and p.dropDuplicates(k).join(e, k, "left_anti").count() > 0


def test_scope_replacement_recovery_and_drain(spark, sf):
    tags = event_tags(spark, sf)
    marks = tags.groupBy("scope").agg(F.max("us").alias("watermark"))
    store = projection.Store(spark)
    projection.project_scopes(store, tags, marks.filter("scope <> 3"), [links.R1], "g1")
    late = projection.recover(store, tags, marks, [links.R1], "g1")
    assert [r["scope"] for r in late.collect()] == [3]
    want = links.derive(tags, links.R1)
    assert measures.jaccard(store.links(), want, ["link_id"]).first()["jaccard_ppm"] == 1_000_000
    classed = marks.withColumn("class", (F.col("scope") % 3 + 1).cast("int"))
    pages = projection.drain(store, tags, classed, [links.R2], "g2", 6)
    assert measures.drain_inversions(pages) == 0 and projection.backlog(classed, store.state(), "g2").count() == 0
    assert measures.jaccard(store.links(), links.derive(tags, links.R2), ["link_id"]).first()["jaccard_ppm"] == 1_000_000


def test_signature_vector_and_verdicts(spark):
    # first test vector of the signature standard
    seed = bytes.fromhex("9d61b19deffd5a60ba844af492ec2cc44449c5697b326919703bac031cae7f60")
    public = trust.public_key(seed)
    assert public.hex() == "d75a980182b10ab7d54bfed3c964073a0ee172f3daa62325af021a68f707511a"
    s = trust.sign(seed, b"")
    assert trust.verify_one(public, b"", s) and not trust.verify_one(public, b"x", s)
    key = trust.Key("k", 1, public.hex(), ("clinical_origin",), (7,), 0, 1000, None)
    rows = [trust.attest("s", "clinical_origin", key, seed, "a", 10), trust.attest("s", "exchange_import", key, seed, "a", 10), trust.attest("s", "clinical_origin", key, seed, "a", 2000)]
    forged = list(rows[0])
    forged[0] = "other"
    df = spark.createDataFrame([*rows, tuple(forged)], trust.ATTESTATION)
    assert sorted(r["verdict"] for r in trust.verify(df, trust.key_table(spark, [key]), 7).collect()) == ["purpose", "subject", "valid", "validity"]
    assert {r["verdict"] for r in trust.verify(df, trust.key_table(spark, [key]), 8).collect()} == {"tenant"}


def test_gate_rejects_warning_without_evidence(spark):
    rows = [("a", "warning", "curated", "r", "known"), ("b", "warning", "curated", "r", ""), ("c", "warning", "proposed", "r", "known"), ("d", "info", "proposed", "r", "")]
    df = spark.createDataFrame(rows, "link_id string, severity string, basis string, rule_id string, evidence_id string")
    ok, no = links.escalation_gate(df, spark.createDataFrame([("known",)], "evidence_id string"))
    assert {r["link_id"] for r in ok.collect()} == {"a", "d"} and {(r["link_id"], r["reason"]) for r in no.collect()} == {("b", "evidence"), ("c", "basis")}


def test_context_never_shows_hidden_and_tells_what_it_cut(spark):
    nodes = spark.createDataFrame([(k, 1, 2 if k == 3 else 0, None if k == 4 else k, 10, k) for k in range(1, 8)], "node long, scope long, level int, current long, tokens long, us long")
    ls = spark.createDataFrame([(1, 1, 2, 0, 9, "r"), (1, 1, 3, 0, 8, "r"), (1, 1, 4, 0, 7, "r"), (1, 1, 5, 0, 6, "r"), (1, 5, 6, 0, 5, "r"), (1, 3, 7, 0, 5, "r")], "scope long, src long, dst long, rank_severity int, score long, rule_id string")
    anchors = spark.createDataFrame([(100, 1, 1)], "anchor long, node long, scope long")
    r = retrieval.retrieve_many(anchors, nodes, ls, clearance.Caller("researcher"))
    assert {(x["node"], x["hop"]) for x in r.nodes.collect()} == {(1, 0), (2, 1), (5, 1)}
    assert {(x["node"], x["cause"]) for x in r.truncated.collect()} == {(6, "depth")}
    r = retrieval.retrieve_many(anchors, nodes, ls, clearance.Caller("researcher"), retrieval.Limits(per_node=1, tokens=15))
    assert {x["node"] for x in r.nodes.collect()} == {1} and {(x["node"], x["cause"]) for x in r.truncated.collect()} == {(5, "links"), (2, "tokens")}


def test_cycle_is_found(spark):
    e = spark.createDataFrame([("b", "a"), ("c", "b"), ("x", "y"), ("y", "x")], "child string, parent string")
    assert {r["node"] for r in structure.check_dag(e).collect()} == {"x", "y"}


def test_plans_prune_and_do_not_cross(spark, sf):
    text = links.derive(item_tags(spark, sf), links.R3)._jdf.queryExecution().toString()
    assert "CartesianProduct" not in text and "BroadcastNestedLoopJoin" not in text and "Python" not in text
    plan = spark.read.parquet(f"{sf}/lineitem.parquet").filter("l_returnflag = 'R'").select("l_orderkey")._jdf.queryExecution().toString()
    assert "PushedFilters: [IsNotNull(l_returnflag), EqualTo(l_returnflag,R)]" in plan


def test_entry_contract(spark, sf):
    import __spark_entry__ as e

    assert e.entry(spark).count() > 0
    assert set(e.oracle_sql()) <= set(e.queries()) and len(e.queries()) > 230


def test_store_reopens_repeats_and_refuses(spark, sf):
    tags = event_tags(spark, sf)
    marks = tags.groupBy("scope").agg(F.max("us").alias("watermark"))
    store = projection.Store(spark)
    run = projection.project_scopes(store, tags, marks, [links.R1], "g1")
    assert projection.project_scopes(projection.Store(spark, store.root), tags, marks, [links.R1], "g1") == run
    want = links.derive(tags, links.R1).count()
    assert store.links().count() == want and store.manifests().count() == 1
    projection.project_scopes(projection.Store(spark, store.root), tags, marks, [links.R2], "g2")
    assert {r["generation"] for r in store.state().collect()} == {"g2"}
    assert store.compacted().links().count() == store.links().count()
    other = projection.project_scopes(store, tags.withColumn("k", F.col("k") + 1), marks, [links.R1], "g1")
    assert other != run  # other facts, another run


def test_cycle_check_closure_and_roots_over_long_chains(spark):
    chain = spark.createDataFrame([(f"n{k + 1}", f"n{k}") for k in range(45)], "child string, parent string")
    assert structure.check_dag(chain).count() == 0
    ring = chain.unionByName(spark.createDataFrame([("n10", "n20")], "child string, parent string"))
    assert {r["node"] for r in structure.check_dag(ring).collect()} == {f"n{k}" for k in range(10, 21)}
    far = structure.closure(spark.createDataFrame([("n25",)], "seed string"), chain).agg(F.max("distance")).first()[0]
    assert far == 20 and structure.closure(spark.createDataFrame([("n15",)], "seed string"), ring, max_depth=8).filter("distance > 0").count() == 11
    c = chain.filter("length(child) = 2").groupBy(F.col("child").alias("capsule_id")).agg(F.collect_list("parent").alias("parents")).unionByName(spark.createDataFrame([("n0", [])], "capsule_id string, parents array<string>")).withColumn("scope_root", F.lit("n0"))
    assert {tuple(r["roots"]) for r in structure.scope_of(c).collect()} == {("n0",)}


def test_links_of_an_amended_record_lead_to_the_current_one(spark):
    nodes = spark.createDataFrame([(1, 1, 0, 1, 1), (2, 1, 0, 3, 1), (3, 1, 0, 3, 1), (4, 1, 0, None, 1), (5, 1, 2, 5, 1)], "node long, scope long, level int, current long, tokens long")
    ls = spark.createDataFrame([(1, 1, 2, 0, 9, "r"), (1, 2, 3, 0, 9, "r"), (1, 1, 4, 0, 8, "r"), (1, 3, 5, 1, 8, "r")], "scope long, src long, dst long, rank_severity int, score long, rule_id string")
    r = retrieval.retrieve_many(spark.createDataFrame([(7, 1, 1)], "anchor long, node long, scope long"), nodes, ls, clearance.Caller("nurse"))
    assert {(x["node"], x["hop"], x["via"]) for x in r.nodes.collect()} == {(1, 0, None), (3, 1, 1)} and r.report.first()["complete"]
    old = retrieval.retrieve_many(spark.createDataFrame([(7, 2, 1)], "anchor long, node long, scope long"), nodes, ls, clearance.Caller("nurse"))
    assert {(x["node"], x["hop"]) for x in old.nodes.collect()} == {(3, 0), (1, 1)}


def test_spine_of_a_context_stops_at_hidden_containers(spark):
    nodes = spark.createDataFrame([(k, 1, 2 if k == 3 else 0, k, 1) for k in range(1, 8)], "node long, scope long, level int, current long, tokens long")
    spine = spark.createDataFrame([(2, 1), (3, 1), (4, 2), (5, 3), (6, 4), (7, 6)], "child long, parent long")
    none = spark.createDataFrame([], "scope long, src long, dst long, rank_severity int, score long, rule_id string")
    r = retrieval.retrieve_many(spark.createDataFrame([(9, 1, 1)], "anchor long, node long, scope long"), nodes, none, clearance.Caller("nurse"), retrieval.Limits(down=2), spine=spine)
    assert {(x["node"], x["reason"]) for x in r.nodes.collect()} == {(1, "anchor"), (2, "spine:down"), (4, "spine:down")}
    assert {(x["node"], x["cause"]) for x in r.truncated.collect()} == {(6, "spine")}


def test_spans_of_the_window_lose_no_pair(spark):
    rows = [(k, 1, k * 7_000_000_000 * (1 + k % 3), k % 5, "etype", "x") for k in range(120)]
    tags = spark.createDataFrame(rows, "node long, scope long, us long, k int, ns string, code string")
    got = {(r["src"], r["dst"]) for r in links.candidates(tags, links.R1).collect()}
    at = {r[0]: r[2] for r in rows}
    want = {(a, b) for a in at for b in at if (at[a], a) < (at[b], b) and at[b] - at[a] <= links.R1.window_us}
    assert got == want and links.candidates(tags, links.R1).count() == len(want)


def test_jvm_signatures_agree(spark):
    seed, message = bytes(range(32)), b"said"
    public = trust.public_key(seed)
    assert trust.jvm_sign(spark, seed, message) == trust.sign(seed, message)
    assert trust.jvm_verify(spark, public, message, trust.sign(seed, message)) and not trust.jvm_verify(spark, public, b"other", trust.sign(seed, message))
    assert not trust.jvm_verify(spark, b"short", message, b"x")


def test_canonical_numbers_and_keys():
    assert canonical_text('[333333333.33333329,1E30,4.50,2e-3,0.000000000000000000000000001,-0.0,1e21,123456789012345680000,1e-7]') == "[333333333.3333333,1e+30,4.5,0.002,1e-27,0,1e+21,123456789012345680000,1e-7]"
    assert canonical_text('{"\\u20ac":1,"\\ud83d\\ude00":2,"\\ufb33":3}') == '{"\u20ac":1,"\U0001f600":2,"\ufb33":3}'


def test_communities_report(spark):
    m = spark.createDataFrame([(d, e) for d in range(3) for e in ("aa", "bb")] + [(5, "aa")], "doc_id long, entity string")
    r = baselines.community_reports(m, spark.createDataFrame([("aa", "aa"), ("bb", "aa")], "entity string, community string")).collect()
    assert [(x["entities"], x["documents"], x["report"]) for x in r] == [(2, 4, "aa (4), bb (3)")]


def test_lines_without_a_neighbour_get_no_id(spark, sf):
    only = lines_meeting(spark, sf, links.R3)
    few = item_tags(spark, sf, links.R3).select("node").distinct().count()
    every = links.score(links.candidates(item_tags(spark, sf), links.R3), links.R3)
    some = links.score(links.candidates(item_tags(spark, sf, links.R3), links.R3), links.R3)
    assert 0 < only.count() and few < ingest.items(spark, sf).count() // 4
    assert sorted(map(tuple, some.collect())) == sorted(map(tuple, every.collect())) != []
    rows = spark.createDataFrame([(1, 0), (1, 10), (1, 21), (2, 5), (None, 0), (None, 1), (3, None), (3, 1)], "g int, at int")
    assert sorted(map(tuple, links.neighboured(rows, ["g"], "at", 10).collect())) == [(1, 0), (1, 10)]


def test_pairs_across_scopes_are_counted_not_made(spark):
    import random

    r = random.Random(3)
    rows = [(k, r.choice([1, 2, None]), r.choice([None, *range(0, 40, 3)]), "etype", r.choice(["a", "b", None])) for k in range(120)]
    tags = spark.createDataFrame(rows, "node long, scope long, us long, ns string, code string")
    for window in (0, 7, 12):
        near = [(a, b) for a in rows for b in rows if None not in (a[2], b[2], a[4], b[4]) and a[4] == b[4] and 0 < b[2] - a[2] <= window]
        cross = sum(None not in (a[1], b[1]) and a[1] != b[1] for a, b in near)
        df = baselines.unscoped_links(tags, links.LinkRule("x", "y", ("etype",), window, 1))
        assert tuple(df.first()) == (len(near), cross)
    assert "SortMergeJoin" not in df._jdf.queryExecution().toString() and "BroadcastHashJoin" not in df._jdf.queryExecution().toString()


def test_candidates_are_not_joined_by_broadcast(spark):
    tags = spark.createDataFrame([(1, 1, 1, 1, "etype", "a"), (2, 1, 2, 1, "etype", "a")], "node long, scope long, us long, k int, ns string, code string")
    c = links.candidates(tags, links.R1)
    assert c.count() == 1 and "SortMergeJoin" in c._jdf.queryExecution().toString()


def test_recursive_closure_of_many_rows(spark, sf):
    was = spark.conf.get("spark.sql.cteRecursionRowLimit")
    spark.conf.set("spark.sql.cteRecursionRowLimit", "50")
    try:
        assert scenarios.closure_recursive_sql(spark, sf).count() > 50
    finally:
        spark.conf.set("spark.sql.cteRecursionRowLimit", was)


def test_lint_and_paged_source_read_the_tables(spark, sf):
    from evigraph import surface, workloads

    n = ingest.read(spark, sf, "orders").filter("o_orderkey % 8 > 2").groupBy((F.col("o_orderkey") % 8).cast("int")).agg(F.count("*"), F.sum("o_orderkey"))
    assert sorted(map(tuple, surface.op_source_paged(spark, sf).collect())) == sorted(map(tuple, n.collect())) != []
    lint = workloads.lineage_lint(spark, sf)
    assert lint.first()[0] == 0 and any("lineitem.parquet" in f for f in lint.inputFiles())


def test_without_links_no_node_is_dealt_out_for_them(spark):
    nodes = spark.createDataFrame([("a", 1, 0, "a", 1), ("b", 1, 0, "b", 1)], "node string, scope long, level int, current string, tokens long")
    anchors = spark.createDataFrame([(1, "a", 1)], "anchor long, node string, scope long")
    none = spark.createDataFrame([], "scope long, src string, dst string, rank_severity int, score long, rule_id string")
    r = retrieval.retrieve_many(anchors, nodes, none, clearance.Caller("nurse"), spine=spark.createDataFrame([("b", "a")], "child string, parent string"), limits=retrieval.Limits(down=1))
    assert sorted(x["node"] for x in r.nodes.collect()) == ["a", "b"]
    assert "rank_severity" not in r.report._jdf.queryExecution().optimizedPlan().toString()


def test_communities_without_all_pairs(spark):
    # one large part by its commonest entities, two of rare ones, a pair met once, a document given twice or without an id
    rows = [(d, f"big{(d + k) % 40:02d}") for d in range(80) for k in range(12)]
    rows += [(100 + d, f"tail{e}") for d in (0, 1) for e in range(50)] + [(200 + d, f"far{e}") for d in (0, 1) for e in range(3)]
    rows += [(100, "big00"), (300, "once"), (300, "tail7"), (None, "aaa"), (None, "tail1"), (None, "aaa"), (400, "twice"), (400, "twice"), (400, "far2")]
    got = {r["entity"]: r["community"] for r in baselines.community_graph(spark.createDataFrame(rows, "doc_id long, entity string"), hubs=(1, None)).collect()}
    parts = {"big00": {f"big{k:02d}" for k in range(40)}, "tail0": {f"tail{k}" for k in range(50)}, "far0": {"far0", "far1", "far2", "twice"}}
    assert got == {e: name for name, own in parts.items() for e in own}
    # what is known already is not paired again
    batch = pa.RecordBatch.from_pydict({"ids": [[7, 3, 5, 9]], "n": [[1, 1, 1, 2]], "own": [[9]], "parts": [[9]]})
    made = [r for b in baselines._across(None, 3)(iter([batch])) for r in b.to_pylist()]
    assert sorted((r["x"], r["y"], r["w"]) for r in made) == [(3, 9, 2), (5, 9, 2), (7, 9, 2)]


def test_packs_deal_rows_once(spark, sf, tmp_path):
    c = ingest.star(spark, sf).select(CAPSULE)
    n, store = c.count(), str(tmp_path / "store")
    pack.append(c.unionByName(c.limit(100)), store, buckets=4)
    p = spark.read.parquet(store)
    assert p.count() == p.select("capsule_id").distinct().count() == n
    want = sorted(map(tuple, pack.frames(c, None, 4).select("capsule_id", "pack_seq", "frame_crc", "pack_bucket").collect()))
    again = pack.copied(p, str(tmp_path / "copy"))
    assert sorted(map(tuple, again.select("capsule_id", "pack_seq", "frame_crc", "pack_bucket").collect())) == want
    assert all(".zstd." in f for f in [*p.inputFiles(), *again.inputFiles()])


def test_reconstruction_part_by_part(spark, sf, monkeypatch):
    """Parts hold each capsule once, every part's packs and tables go before the next are written, and the rows are those
    of the whole."""
    whole = {r["family"]: (r["same"], r["n"]) for r in workloads.reconstruction(spark, sf).collect()}
    rows = sum(ingest.read(spark, sf, t).count() for t in ("orders", "lineitem"))
    monkeypatch.setattr(store, "PART_ROWS", rows // 3 + 1)
    parts = ingest.parts(spark, sf, "orders", "lineitem")
    apart = [workloads.scoped(spark, sf, p).select("capsule_id") for p in parts]
    assert len(parts) == 3 and all(p.count() > 0 for p in apart)
    together = reduce(DataFrame.unionAll, apart)
    assert together.exceptAll(workloads.scoped(spark, sf).select("capsule_id")).count() == 0 and together.count() == workloads.scoped(spark, sf).count()
    stored = []
    monkeypatch.setattr(pack, "copied", lambda p, path, copied=pack.copied: stored.append((path, [x for x, _ in stored if pack.exists(spark, x)])) or copied(p, path))
    assert {r["family"]: (r["same"], r["n"]) for r in workloads.reconstruction(spark, sf).collect()} == whole
    assert len(stored) > 3 and all(left == [stored[0][0]] for _, left in stored[1:]) and not any(pack.exists(spark, x) for x, _ in stored)


def test_reconstruction_tells_a_damaged_part(spark, sf, monkeypatch):
    """A capsule that one copy lost makes its families differ, whichever part it is in."""
    monkeypatch.setattr(store, "PART_ROWS", 4000)
    monkeypatch.setattr(pack, "copied", lambda p, path, copied=pack.copied: copied(p.filter("kind <> 'episode' or get_json_object(body, '$.key') <> '7'"), path))
    same = {r["family"]: r["same"] for r in workloads.reconstruction(spark, sf).collect()}
    assert not same["objects"] and not same["edges"] and not same["text"] and same["tags"] and same["status"] and same["therapies"]


def test_hidden_block_part_by_part(spark, sf, monkeypatch):
    """The answers of all parts are those of the whole, none is there twice, and a part's nodes go before the next part's are
    written."""
    whole = sorted(map(tuple, scenarios.expand_hidden_block(spark, sf).collect()))
    monkeypatch.setattr(store, "PART_ROWS", 4000)
    made = []
    monkeypatch.setattr(scenarios, "_spine", lambda s, d, part, spine=scenarios._spine: made.append((got := spine(s, d, part), sum(pack.exists(s, f) for (n, _), _ in made for f in n.inputFiles()))) or got)
    assert sorted(map(tuple, scenarios.expand_hidden_block(spark, sf).collect())) == whole
    assert len(whole) == ingest.read(spark, sf, "customer").count() and len(made) > 1 and not any(left for _, left in made)
