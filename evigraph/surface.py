"""Queries of the surrounding operators a user of the methods needs, and of the streaming forms."""

from __future__ import annotations

import pandas as pd
from pyspark.sql import DataFrame, SparkSession, Window
from pyspark.sql import functions as F
from pyspark.sql.types import LongType, StringType, StructField, StructType

from evigraph.plans.store import path_for, written
from evigraph.sources.ingest import observed, read
from evigraph.streaming import flows
from evigraph.workloads import query


@query("SELECT p.event_id, (SELECT max(v.event_id) FROM events v WHERE v.user_id = p.user_id AND v.event_type = 'view' AND v.event_id < p.event_id) AS last_view FROM events p WHERE p.event_type = 'purchase' AND EXISTS (SELECT 1 FROM events v WHERE v.user_id = p.user_id AND v.event_type = 'view' AND v.event_id < p.event_id)")
def op_asof_join(s: SparkSession, d: str) -> DataFrame:
    """Each purchase with the latest earlier view of its user: one window over the union, no range join."""
    e = observed(s, d)
    w = Window.partitionBy("user_id").orderBy("us", "event_id").rowsBetween(Window.unboundedPreceding, -1)
    e = e.withColumn("last_view", F.last(F.when(F.col("event_type") == "view", F.col("event_id")), True).over(w))
    return e.filter("event_type = 'purchase' and last_view is not null").select("event_id", "last_view")


@query("SELECT o_orderkey, CASE WHEN year(o_orderdate) < 1997 THEN 'a' WHEN year(o_orderdate) < 2000 THEN 'b' ELSE 'c' END AS era FROM orders")
def op_interval_join(s, d):
    eras = s.createDataFrame([("a", 0, 1997), ("b", 1997, 2000), ("c", 2000, 9999)], "era string, y0 int, y1 int")
    o = read(s, d, "orders").withColumn("y", F.year("o_orderdate"))
    return o.join(F.broadcast(eras), (o["y"] >= eras["y0"]) & (o["y"] < eras["y1"])).select("o_orderkey", "era")


@query("SELECT a.event_id AS a, b.event_id AS b FROM events a JOIN events b ON a.user_id = b.user_id AND epoch_us(b.ts) > epoch_us(a.ts) AND epoch_us(b.ts) - epoch_us(a.ts) <= 3600000000")
def op_range_join(s, d):
    """Events of one user within an hour: equi-join on time bins and their neighbours, then the exact gap."""
    e = observed(s, d).select("user_id", "event_id", "us")
    hour = 3_600_000_000
    a = e.select("user_id", F.col("event_id").alias("a"), F.col("us").alias("ua"), F.explode(F.array(F.expr(f"us div {hour}"), F.expr(f"us div {hour} + 1"))).alias("bin"))
    b = e.select("user_id", F.col("event_id").alias("b"), F.col("us").alias("ub"), F.expr(f"us div {hour}").alias("bin"))
    return a.join(b, ["user_id", "bin"]).filter((F.col("ub") > F.col("ua")) & (F.col("ub") - F.col("ua") <= hour)).select("a", "b")


@query("SELECT c_custkey FROM customer WHERE c_custkey IN (SELECT user_id FROM events)")
def op_semi(s, d):
    return read(s, d, "customer").select("c_custkey").join(read(s, d, "events").select(F.col("user_id").alias("c_custkey")), "c_custkey", "left_semi")


@query("SELECT c_custkey FROM customer WHERE c_custkey NOT IN (SELECT o_custkey FROM orders)")
def op_anti(s, d):
    return read(s, d, "customer").select("c_custkey").join(read(s, d, "orders").select(F.col("o_custkey").alias("c_custkey")), "c_custkey", "left_anti")


@query("SELECT coalesce(s_nationkey, c_nationkey) AS nation, coalesce(s, 0) AS s, coalesce(c, 0) AS c FROM (SELECT s_nationkey, count(*) AS s FROM supplier GROUP BY 1) FULL JOIN (SELECT c_nationkey, count(*) AS c FROM customer GROUP BY 1) ON s_nationkey = c_nationkey")
def op_full_outer(s, d):
    a = read(s, d, "supplier").groupBy(F.col("s_nationkey").alias("nation")).agg(F.count("*").alias("s"))
    b = read(s, d, "customer").groupBy(F.col("c_nationkey").alias("nation")).agg(F.count("*").alias("c"))
    return a.join(b, "nation", "full_outer").fillna(0)


@query("SELECT r_name, n_name FROM region, nation")
def op_cross(s, d):
    return read(s, d, "region").select("r_name").crossJoin(F.broadcast(read(s, d, "nation").select("n_name")))


@query("SELECT a.r_regionkey AS a, b.r_regionkey AS b FROM region a JOIN region b ON a.r_regionkey < b.r_regionkey")
def op_nested_loop(s, d):
    r = read(s, d, "region").select("r_regionkey")
    return r.withColumnRenamed("r_regionkey", "a").join(F.broadcast(r.withColumnRenamed("r_regionkey", "b")), F.col("a") < F.col("b"))


_NAT = "customer JOIN nation ON n_nationkey = c_nationkey"


def _nat(s, d):
    return read(s, d, "customer").join(F.broadcast(read(s, d, "nation")), F.col("c_nationkey") == F.col("n_nationkey"))


@query(f"SELECT coalesce(n_regionkey, -1) AS tenant, coalesce(n_nationkey, -1) AS organization, count(*) AS n FROM {_NAT} GROUP BY ROLLUP (n_regionkey, n_nationkey)")
def op_rollup(s, d):
    return _nat(s, d).rollup(F.col("n_regionkey").alias("tenant"), F.col("n_nationkey").alias("organization")).agg(F.count("*").alias("n")).fillna(-1)


@query("SELECT coalesce(o_orderstatus, '*') AS status, coalesce(o_orderpriority, '*') AS priority, count(*) AS n FROM orders GROUP BY CUBE (o_orderstatus, o_orderpriority)")
def op_cube(s, d):
    return read(s, d, "orders").cube(F.col("o_orderstatus").alias("status"), F.col("o_orderpriority").alias("priority")).agg(F.count("*").alias("n")).fillna("*")


@query("SELECT coalesce(l_returnflag, '*') AS flag, coalesce(l_linestatus, '*') AS state, count(*) AS n FROM lineitem GROUP BY GROUPING SETS ((l_returnflag), (l_linestatus))")
def op_grouping_sets(s, d):
    i = read(s, d, "lineitem").select(F.col("l_returnflag").alias("flag"), F.col("l_linestatus").alias("state"))
    return i.groupingSets([["flag"], ["state"]], "flag", "state").agg(F.count("*").alias("n")).fillna("*")


@query("SELECT o_orderpriority AS priority, count(*) FILTER (o_orderstatus = 'F') AS f, count(*) FILTER (o_orderstatus = 'O') AS o, count(*) FILTER (o_orderstatus = 'P') AS p FROM orders GROUP BY 1")
def op_pivot(s, d):
    return read(s, d, "orders").groupBy(F.col("o_orderpriority").alias("priority")).pivot("o_orderstatus", ["F", "O", "P"]).agg(F.count(F.lit(1))).fillna(0).toDF("priority", "f", "o", "p")


@query("SELECT l_returnflag AS flag, count(DISTINCT l_partkey) AS parts, count(DISTINCT l_suppkey) AS suppliers FROM lineitem GROUP BY 1")
def op_distinct_agg(s, d):
    return read(s, d, "lineitem").groupBy(F.col("l_returnflag").alias("flag")).agg(F.count_distinct("l_partkey").alias("parts"), F.count_distinct("l_suppkey").alias("suppliers"))


@query("SELECT o_orderstatus AS status, quantile_disc(o_orderkey, 0.5) AS med FROM orders GROUP BY 1")
def op_percentile(s, d):
    return read(s, d, "orders").groupBy(F.col("o_orderstatus").alias("status")).agg(F.expr("percentile_disc(0.5) within group (order by o_orderkey)").cast("long").alias("med"))


@query("SELECT o_orderkey, rank() OVER w AS r, dense_rank() OVER w AS dr, ntile(4) OVER w2 AS q FROM orders WINDOW w AS (PARTITION BY o_custkey ORDER BY o_orderdate), w2 AS (PARTITION BY o_custkey ORDER BY o_orderdate, o_orderkey)")
def op_window_rank(s, d):
    w = Window.partitionBy("o_custkey").orderBy("o_orderdate")
    return read(s, d, "orders").select("o_orderkey", F.rank().over(w).alias("r"), F.dense_rank().over(w).alias("dr"), F.ntile(4).over(w.orderBy("o_orderdate", "o_orderkey")).alias("q"))


@query("SELECT o_orderkey, count(*) OVER (PARTITION BY o_custkey ORDER BY o_orderkey ROWS BETWEEN 2 PRECEDING AND CURRENT ROW) AS n3, max(o_orderkey) OVER (PARTITION BY o_custkey) AS last FROM orders")
def op_window_frames(s, d):
    w = Window.partitionBy("o_custkey")
    return read(s, d, "orders").select("o_orderkey", F.count("*").over(w.orderBy("o_orderkey").rowsBetween(-2, 0)).alias("n3"), F.max("o_orderkey").over(w).alias("last"))


@query("SELECT event_id, coalesce(lag(event_id) OVER w, -1) AS before, coalesce(lead(event_id) OVER w, -1) AS after FROM events WINDOW w AS (PARTITION BY user_id ORDER BY event_id)")
def op_lag_lead(s, d):
    w = Window.partitionBy("user_id").orderBy("event_id")
    return read(s, d, "events").select("event_id", F.lag("event_id", 1, -1).over(w).alias("before"), F.lead("event_id", 1, -1).over(w).alias("after"))


@query("SELECT user_id, event_id FROM (SELECT *, row_number() OVER (PARTITION BY user_id ORDER BY ts DESC, event_id DESC) AS r FROM events) WHERE r <= 3")
def op_topk(s, d):
    r = F.row_number().over(Window.partitionBy("user_id").orderBy(F.desc("ts"), F.desc("event_id")))
    return read(s, d, "events").withColumn("r", r).filter("r <= 3").select("user_id", "event_id")


@query("SELECT c_custkey FROM customer ORDER BY c_custkey LIMIT 20 OFFSET 40")
def op_offset_page(s, d):
    return read(s, d, "customer").select("c_custkey").orderBy("c_custkey").offset(40).limit(20)


@query("SELECT o_custkey AS k FROM orders UNION SELECT user_id FROM events")
def op_union(s, d):
    return read(s, d, "orders").select(F.col("o_custkey").alias("k")).union(read(s, d, "events").select("user_id")).distinct()


@query("SELECT o_custkey AS k FROM orders INTERSECT SELECT user_id FROM events")
def op_intersect(s, d):
    return read(s, d, "orders").select(F.col("o_custkey").alias("k")).intersect(read(s, d, "events").select("user_id"))


@query("SELECT user_id AS k FROM events EXCEPT ALL SELECT o_custkey FROM orders")
def op_except_all(s, d):
    return read(s, d, "events").select(F.col("user_id").alias("k")).exceptAll(read(s, d, "orders").select("o_custkey"))


@query("SELECT event_id, CAST(json_extract(props, '$.k') AS INTEGER) AS k FROM events")
def op_json(s, d):
    return read(s, d, "events").select("event_id", F.from_json("props", "k int")["k"].alias("k"))


@query()
def op_variant(s, d):
    return read(s, d, "events").select("event_id", F.expr("variant_get(parse_json(props), '$.k', 'int')").alias("k"))


@query("SELECT user_id, string_agg(k, ',' ORDER BY k) AS ks, max(k) AS top FROM (SELECT DISTINCT user_id, CAST(json_extract(props, '$.k') AS INTEGER) % 5 AS k FROM events) GROUP BY 1")
def op_array_hof(s, d):
    g = observed(s, d).groupBy("user_id").agg(F.array_sort(F.collect_set(F.col("k") % 5)).alias("ks"))
    return g.select("user_id", F.array_join(F.transform("ks", lambda x: x.cast("string")), ",").alias("ks"), F.aggregate("ks", F.lit(-1), lambda a, x: F.greatest(a, x)).alias("top"))


@query("SELECT user_id, count(*) FILTER (event_type = 'view') AS views, count(*) FILTER (event_type = 'purchase') AS purchases FROM events GROUP BY 1")
def op_map(s, d):
    c = read(s, d, "events").groupBy("user_id", "event_type").agg(F.count("*").alias("n"))
    m = c.groupBy("user_id").agg(F.map_from_entries(F.collect_list(F.struct("event_type", "n"))).alias("m"))
    zero = F.lit(0).cast("long")
    return m.select("user_id", F.coalesce(F.col("m")["view"], zero).alias("views"), F.coalesce(F.col("m")["purchase"], zero).alias("purchases"))


@query("SELECT p_partkey, upper(p_name) AS up, substring(p_brand, 7) AS num, lpad(CAST(p_size AS VARCHAR), 4, '0') AS padded, length(p_type) AS len FROM part")
def op_string(s, d):
    return read(s, d, "part").select("p_partkey", F.upper("p_name").alias("up"), F.substring("p_brand", 7, 100).alias("num"), F.lpad(F.col("p_size").cast("string"), 4, "0").alias("padded"), F.length("p_type").alias("len"))


@query("SELECT o_orderkey, epoch_us(date_trunc('month', o_orderdate)) AS month_us, datediff('day', DATE '1995-01-01', CAST(o_orderdate AS DATE)) AS days FROM orders")
def op_date(s, d):
    return read(s, d, "orders").select("o_orderkey", F.unix_micros(F.date_trunc("month", F.col("o_orderdate").cast("timestamp"))).alias("month_us"), F.datediff(F.col("o_orderdate").cast("date"), F.lit("1995-01-01").cast("date")).alias("days"))


@query("SELECT c_custkey, c_custkey // 7 AS q, c_custkey % 7 AS r, greatest(c_custkey, 100) AS g, abs(50 - c_custkey) AS a FROM customer")
def op_math(s, d):
    return read(s, d, "customer").select("c_custkey", F.expr("c_custkey div 7").alias("q"), (F.col("c_custkey") % 7).alias("r"), F.greatest("c_custkey", F.lit(100)).alias("g"), F.abs(50 - F.col("c_custkey")).alias("a"))


@query()
def op_approx_distinct(s, d):
    return read(s, d, "lineitem").agg(F.approx_count_distinct("l_partkey").alias("parts"), F.hll_sketch_estimate(F.hll_sketch_agg("l_suppkey")).alias("suppliers"))


@query("SELECT event_id, '{\"k\":' || CAST(json_extract(props, '$.k') AS INTEGER) || '}' AS canon FROM events")
def op_udf(s, d):
    """The general canonicalizer over the events' properties."""
    from evigraph.functions.canonical import canon_udf

    return read(s, d, "events").select("event_id", canon_udf("props").alias("canon"))


@query("SELECT event_id, word FROM (SELECT event_id, unnest(string_split(event_type || ' ' || user_id, ' ')) AS word FROM events)")
def op_udtf(s, d):
    kind = StructType([StructField("event_id", LongType()), StructField("word", StringType())])

    class Words:
        def eval(self, event_id: int, said: str):
            for w in said.split(" "):
                yield event_id, w

    s.udtf.register("said_words", F.udtf(Words, returnType=kind))
    read(s, d, "events").createOrReplaceTempView("surface_events")
    return s.sql("SELECT w.* FROM surface_events e, LATERAL said_words(e.event_id, concat_ws(' ', e.event_type, cast(e.user_id as string))) w")


@query("SELECT o_orderkey FROM orders WHERE o_orderpriority = '1-URGENT' AND o_orderstatus = 'O'")
def op_sql_args(s, d):
    return s.sql("SELECT o_orderkey FROM {o} WHERE o_orderpriority = :p AND o_orderstatus = :s", args={"p": "1-URGENT", "s": "O"}, o=read(s, d, "orders"))


@query("SELECT (SELECT count(*) FROM orders WHERE o_custkey NOT IN (SELECT c_custkey FROM customer)) AS orphans, (SELECT count(*) - count(DISTINCT c_custkey) FROM customer) AS repeats, (SELECT count(*) FILTER (c_name IS NULL) FROM customer) AS nulls")
def op_quality_checks(s, d):
    o, c = read(s, d, "orders"), read(s, d, "customer")
    a = o.join(c, F.col("o_custkey") == F.col("c_custkey"), "left_anti").agg(F.count("*").alias("orphans"))
    return a.crossJoin(c.agg((F.count("*") - F.count_distinct("c_custkey")).alias("repeats"), F.sum(F.col("c_name").isNull().cast("long")).alias("nulls")))


@query("SELECT CAST(epoch_us(ts) // 86400000000 * 86400000000 AS BIGINT) AS start_us, event_type, count(*) AS n FROM events GROUP BY 1, 2")
def stream_tumbling(s, d):
    return flows.tumbling(s, d)


@query("SELECT start_us, count(*) AS n FROM (SELECT unnest([CAST(epoch_us(ts) // 86400000000 * 86400000000 AS BIGINT), CAST(epoch_us(ts) // 86400000000 * 86400000000 - 86400000000 AS BIGINT)]) AS start_us FROM events) GROUP BY 1")
def stream_sliding(s, d):
    return flows.sliding(s, d)


@query("WITH m AS (SELECT user_id, epoch_us(ts) AS us, CASE WHEN epoch_us(ts) - lag(epoch_us(ts)) OVER (PARTITION BY user_id ORDER BY ts, event_id) < 21600000000 THEN 0 ELSE 1 END AS fresh FROM events), g AS (SELECT user_id, us, sum(fresh) OVER (PARTITION BY user_id ORDER BY us ROWS UNBOUNDED PRECEDING) AS i FROM m) SELECT min(us) AS start_us, user_id, count(*) AS n FROM g GROUP BY user_id, i")
def stream_session(s, d):
    return flows.session(s, d)


@query("SELECT event_id, user_id, event_type FROM events")
def stream_dedupe(s, d):
    return flows.dedupe(s, d)


@query("SELECT c_mktsegment, count(*) AS n FROM events JOIN customer ON c_custkey = user_id GROUP BY 1")
def stream_enriched(s, d):
    return flows.enriched(s, d)


@query("SELECT epoch_us(ts) < 1706140800000000 AS late, count(*) AS n FROM events GROUP BY 1")
def stream_late_audit(s, d):
    return flows.late_audit(s, d, 1_706_140_800_000_000)


@query("SELECT a.event_id AS bought, b.event_id AS signed FROM events a JOIN events b ON a.user_id = b.user_id AND a.event_type = 'purchase' AND b.event_type = 'signup' AND epoch_us(b.ts) >= epoch_us(a.ts) AND epoch_us(b.ts) <= epoch_us(a.ts) + 86400000000")
def stream_interval_join(s, d):
    return flows.interval_join(s, d)


@query("SELECT user_id AS scope, max(event_id) AS watermark FROM events GROUP BY 1")
def stream_scope_projection(s, d):
    out = path_for(s, "touched")
    flows.scope_projection(s, d, lambda touched: touched.write.mode("append").parquet(out))
    return s.read.parquet(out).groupBy("scope").agg(F.max("watermark").alias("watermark"))


# sources and sinks


def _through(df: DataFrame, kind: str, **options) -> DataFrame:
    """Write in a format, and read back with the same columns."""
    path = path_for(df.sparkSession, kind)
    df.write.options(**options).format(kind).save(path)
    return df.sparkSession.read.options(**options).schema(df.schema).format(kind).load(path)


_ORDER = "SELECT o_orderkey, o_orderstatus, o_orderpriority, CAST(round(o_totalprice * 100) AS BIGINT) AS cents FROM orders"


def _orders(s, d) -> DataFrame:
    return read(s, d, "orders").select("o_orderkey", "o_orderstatus", "o_orderpriority", F.round(F.col("o_totalprice") * 100).cast("long").alias("cents"))


for _kind, _options in (("json", {}), ("csv", {"header": "true"}), ("orc", {})):
    query(_ORDER, f"op_source_{_kind}")(lambda s, d, kind=_kind, options=_options: _through(_orders(s, d), kind, **options))


@query("SELECT doc_id, len(string_split(text, chr(10))) AS lines FROM documents WHERE text IS NOT NULL AND doc_id % 10 = 0")
def op_source_text(s, d):
    """Lines of text files, one folder a document, counted by the folder they came from."""
    docs, path = read(s, d, "documents").filter("text is not null and doc_id % 10 = 0"), path_for(s, "text")
    docs.select("doc_id", F.explode(F.split("text", "\n")).alias("value")).write.partitionBy("doc_id").text(path)
    return s.read.text(path).groupBy(F.col("doc_id").cast("long").alias("doc_id")).agg(F.count("*").alias("lines"))


@query("SELECT n_name AS name, length(n_name) + 1 AS bytes FROM nation")
def op_source_binary(s, d):
    """Whole files as binary rows with their sizes."""
    path = path_for(s, "binary")
    read(s, d, "nation").select("n_name", F.col("n_name").alias("value")).write.partitionBy("n_name").text(path)
    files = s.read.format("binaryFile").option("recursiveFileLookup", "true").option("pathGlobFilter", "*.txt").load(path)
    return files.filter("length > 0").select(F.trim(F.decode("content", "UTF-8"), F.lit("\n")).alias("name"), F.col("length").cast("long").alias("bytes"))


@query("SELECT CAST(o_orderkey % 8 AS INTEGER) AS page, count(*) AS n, sum(o_orderkey)::BIGINT AS keys FROM orders WHERE o_orderkey % 8 > 2 GROUP BY 1")
def op_source_paged(s, d):
    """The paged source of our own over an export of the orders, from its third page on."""
    from evigraph.sources.paged import PagedSource, exported

    path = path_for(s, "pages")
    exported(read(s, d, "orders").select((F.col("o_orderkey") % 8).cast("int").alias("page"), F.col("o_orderkey").alias("logical"), F.col("o_orderstatus").alias("version")), path)
    s.dataSource.register(PagedSource)
    return s.read.format("evigraph_paged").options(path=path, pages=8, since=2).load().groupBy("page").agg(F.count("*").alias("n"), F.sum("logical").alias("keys"))


@query("SELECT o_orderstatus AS status, count(*) AS n, 1 AS files FROM orders GROUP BY 1")
def op_sink_compaction(s, d):
    """Many small files of a partition, overwritten by one each; partitions that are not written stay."""
    from evigraph.plans.baselines import laid_out

    path = path_for(s, "compacted")
    o = read(s, d, "orders").select(F.col("o_orderkey").alias("capsule_id"), F.col("o_orderstatus").alias("status"))
    o.repartition(6).write.partitionBy("status").parquet(path)
    whole = written(s.read.parquet(path))
    whole.repartition("status").write.mode("overwrite").option("partitionOverwriteMode", "dynamic").partitionBy("status").parquet(path)
    got = s.read.parquet(path)
    assert laid_out(got).first()["files"] < 6 * 3
    return got.groupBy("status").agg(F.count("*").alias("n"), F.count_distinct(F.col("_metadata.file_path")).cast("int").alias("files"))


@query("SELECT c_mktsegment AS segment, count(*) AS n FROM customer GROUP BY 1")
def op_sink_bucketed(s, d):
    """A bucketed and sorted table, joined to itself on the bucket column without an exchange of it."""
    name = f"evigraph_bucketed_{path_for(s, 'b').rpartition('-')[2]}"
    read(s, d, "customer").write.bucketBy(4, "c_custkey").sortBy("c_custkey").format("parquet").option("path", path_for(s, "bucketed")).saveAsTable(name)
    t = s.table(name)
    out = written(t.join(t.select("c_custkey"), "c_custkey").groupBy(F.col("c_mktsegment").alias("segment")).agg(F.count("*").alias("n")))
    s.sql(f"DROP TABLE {name}")
    return out


# windows, functions and views that the methods lean on


@query("SELECT o_orderkey, CAST(round(percent_rank() OVER w * 1000000) AS BIGINT) AS pr, CAST(round(cume_dist() OVER w * 1000000) AS BIGINT) AS cd, coalesce(nth_value(o_orderkey, 2) OVER (PARTITION BY o_custkey ORDER BY o_orderdate, o_orderkey ROWS BETWEEN UNBOUNDED PRECEDING AND UNBOUNDED FOLLOWING), -1) AS second FROM orders WINDOW w AS (PARTITION BY o_custkey ORDER BY o_orderdate)")
def op_window_shares(s, d):
    w = Window.partitionBy("o_custkey").orderBy("o_orderdate")
    whole = Window.partitionBy("o_custkey").orderBy("o_orderdate", "o_orderkey").rowsBetween(Window.unboundedPreceding, Window.unboundedFollowing)
    micro = lambda c: F.round(c * 1_000_000).cast("long")
    return read(s, d, "orders").select("o_orderkey", micro(F.percent_rank().over(w)).alias("pr"), micro(F.cume_dist().over(w)).alias("cd"), F.coalesce(F.nth_value("o_orderkey", 2).over(whole), F.lit(-1)).alias("second"))


@query("SELECT event_id, count(*) OVER (PARTITION BY user_id ORDER BY ts RANGE BETWEEN INTERVAL 1 DAY PRECEDING AND CURRENT ROW) AS n FROM events")
def op_window_range(s, d):
    """Events of the user in the day up to each, by a frame of time."""
    read(s, d, "events").createOrReplaceTempView("surface_events_by_time")
    return s.sql("SELECT event_id, count(*) OVER (PARTITION BY user_id ORDER BY ts RANGE BETWEEN INTERVAL 1 DAY PRECEDING AND CURRENT ROW) AS n FROM surface_events_by_time")


@query("SELECT o_orderstatus AS status, count(*) AS n, sum(o_orderkey)::BIGINT AS total FROM orders GROUP BY 1")
def op_grouped_pandas(s, d):
    """A grouped aggregate in pandas beside the native one."""
    @F.pandas_udf("long")
    def total(x: pd.Series) -> int:
        return int(x.sum())

    return read(s, d, "orders").groupBy(F.col("o_orderstatus").alias("status")).agg(total("o_orderkey").alias("total")).join(read(s, d, "orders").groupBy(F.col("o_orderstatus").alias("status")).agg(F.count("*").alias("n")), "status")


@query("SELECT c_custkey AS key, 'bad_crc' AS fault FROM customer WHERE c_custkey % 25 = 0")
def op_udtf_frames(s, d):
    """Frames checked by a table function called from SQL."""
    import zlib

    from evigraph.sources import ingest, pack

    kind = StructType([StructField("key", LongType()), StructField("fault", StringType())])

    class VerifyFrames:
        def eval(self, key: int, content: str, crc: int):
            if zlib.crc32(content.encode()) != crc:
                yield key, "bad_crc"

    s.udtf.register("verify_frames", F.udtf(VerifyFrames, returnType=kind))
    f = pack.frames(ingest.subjects(s, d)).withColumn("key", F.get_json_object("body", "$.key").cast("long"))
    content = F.concat_ws("|", "capsule_id", "kind", "body", F.col("clinical_us").cast("string"), F.array_join("parents", ","), "amends", "retracts", "author_id")
    f.select("key", content.alias("content"), (F.col("frame_crc") + (F.col("key") % 25 == 0).cast("int")).alias("crc")).createOrReplaceTempView("surface_frames")
    return s.sql("SELECT v.* FROM surface_frames f, LATERAL verify_frames(f.key, f.content, f.crc) v")


@query("SELECT user_id AS scope, count(*) AS n FROM events WHERE CAST(json_extract(props, '$.k') AS INTEGER) < 90 GROUP BY 1")
def op_secure_view(s, d):
    """A view with the caller's clearance built in: SQL over it cannot reach what the caller may not see."""
    from evigraph.operators import clearance
    from evigraph.workloads import event_nodes

    clearance.visible(event_nodes(s, d), clearance.Caller("nurse")).createOrReplaceTempView("nodes_for_nurse")
    return s.sql("SELECT scope, count(*) AS n FROM nodes_for_nurse GROUP BY scope")
