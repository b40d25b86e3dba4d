"""The rejected alternatives, built to show the contrast."""

from __future__ import annotations

from collections.abc import Callable, Iterator

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame, Window
from pyspark.sql import functions as F

from evigraph.operators import links as L
from evigraph.operators import search
from evigraph.plans.store import bounded, written


def vector_rag(vectors: DataFrame, queries: DataFrame, k: int) -> DataFrame:
    """Similarity of chunks alone: no status, clearance or links."""
    return search.vector_topk(vectors, queries, k)


def lexical_rag(docs: DataFrame, queries: DataFrame, k: int) -> DataFrame:
    post = search.fulltext(docs)
    t = docs.agg(F.count("*").alias("n"), F.avg(F.size(search.terms(F.coalesce("text", F.lit(""))))).alias("m")).first()
    return search.query(post, queries, k, t["n"], t["m"] or 1.0)


def entities(docs: DataFrame, least: int = 3, most_share: float = 0.02) -> DataFrame:
    """(doc_id, entity): long words that several documents share but not too many."""
    w = docs.select("doc_id", F.explode(F.array_distinct(F.filter(search.terms(F.coalesce("text", F.lit(""))), lambda x: F.length(x) >= 8))).alias("entity"))
    n = docs.count()
    df = w.groupBy("entity").agg(F.count("*").alias("df")).filter((F.col("df") >= least) & (F.col("df") <= max(least, int(n * most_share))))
    return w.join(df.select("entity"), "entity", "left_semi")


#: How many of a document's commonest entities its others are paired with, round by round; None: with all.
HUBS = (1, 8, 32, None)


def community_graph(mentions: DataFrame, least: int = 2, max_rounds: int = 200, hubs: tuple[int | None, ...] = HUBS) -> DataFrame:
    """(entity, community): communities are the connected parts of the co-occurrence graph over entities, each
    named by its least one. Pairs inside a part that is known already cannot change it, so they are not
    made: the first rounds pair entities with the commonest ones of their documents only, the last one
    makes every pair whose ends are in different parts."""
    m = written(mentions.filter("doc_id is not null and entity is not null").select("doc_id", "entity"))
    names = written(m.groupBy("entity").agg(F.count("*").alias("df")).withColumn("id", F.monotonically_increasing_id()))
    held = m.join(names, "entity").groupBy("doc_id").agg(F.collect_list(F.struct("df", "id")).alias("of"))
    # each id once, the commonest first, and how many rows of the document name it
    held = held.mapInArrow(_by_rank, "ids array<long>, n array<long>").withColumn("doc", F.monotonically_increasing_id())
    held = written(held)
    label = names.select("id", F.col("id").alias("part"))
    for k in hubs:
        size = label.groupBy("part").agg(F.count("*").alias("n"))
        most = size.orderBy(F.desc("n"), "part").first()
        if most is None:
            break
        other = label if most["n"] == 1 else label.filter(F.col("part") != most["part"])
        met = held.select("doc", F.explode("ids").alias("id")).join(bounded(other), "id").groupBy("doc").agg(F.collect_list("id").alias("own"), F.collect_list("part").alias("parts"))
        pairs = met.join(held, "doc").select("ids", "n", "own", "parts").mapInArrow(_across(k, most["part"]), "x long, y long, p long, q long, w long")
        edges = pairs.groupBy("x", "y", "p", "q").agg(F.sum("w").alias("w")).filter(F.col("w") >= least).select("p", "q").distinct()
        moved = _connected(written(edges), max_rounds)
        label = written(label.join(moved, "part", "left").select("id", F.coalesce("least", "part").alias("part")))
    named = names.select("entity", "id").join(label, "id")
    first = named.groupBy("part").agg(F.min("entity").alias("community"), F.count("*").alias("n")).filter("n > 1")
    return named.join(first, "part").select("entity", "community")


def _by_rank(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
    for batch in batches:
        of = batch.column("of")
        doc, (df, own) = _owner(of), (x.to_numpy() for x in of.flatten().flatten())
        order = np.lexsort((own, -df, doc))
        doc, own = doc[order], own[order]
        first = np.flatnonzero(np.concatenate([[True], (doc[1:] != doc[:-1]) | (own[1:] != own[:-1])])[: len(doc)])
        at = pa.array(np.searchsorted(doc[first], np.arange(len(batch) + 1)), pa.int32())
        n = np.diff(np.append(first, len(doc)))
        yield pa.RecordBatch.from_arrays([pa.ListArray.from_arrays(at, pa.array(own[first])), pa.ListArray.from_arrays(at, pa.array(n))], names=["ids", "n"])


def _owner(lists: pa.Array) -> np.ndarray:
    """Row of each element of a column of lists."""
    return np.repeat(np.arange(len(lists)), np.diff(lists.offsets.to_numpy()))


#: Pairs that are made at once.
PAIRS = 4_000_000


def _across(hubs: int | None, most: int) -> Callable[[Iterator[pa.RecordBatch]], Iterator[pa.RecordBatch]]:
    """Pairs (x, y) of different parts (p, q) of a document, x < y, with their weight: its ``own`` ids, which are
    all that are not of the part ``most``, with its first ``hubs`` ids."""
    def of(ids: np.ndarray, n: np.ndarray, own: np.ndarray, own_parts: np.ndarray) -> Iterator[tuple[np.ndarray, ...]]:
        order = np.argsort(ids)
        own_at = order[np.searchsorted(ids[order], own)]
        part, listed = np.full(len(ids), most, np.int64), np.zeros(len(ids), bool)
        part[own_at], listed[own_at] = own_parts, True
        top = np.arange(min(len(ids), hubs or len(ids)))
        step = max(1, PAIRS // len(top))
        for k in range(0, len(own_at), step):
            a, b = (x.ravel() for x in np.meshgrid(own_at[k : k + step], top, indexing="ij"))
            # two that are both listed and both among the first meet twice, and count once
            some = (part[a] != part[b]) & ~(listed[b] & (a < b) & (a < len(top)))
            a, b = a[some], b[some]
            a, b = np.where(ids[a] < ids[b], a, b), np.where(ids[a] < ids[b], b, a)
            yield ids[a], ids[b], part[a], part[b], n[a] * n[b]

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        kept, size = [], 0
        for batch in batches:
            columns = [(c.offsets.to_numpy(), c.values.to_numpy()) for c in (batch.column(k) for k in ("ids", "n", "own", "parts"))]
            for row in range(len(batch)):
                for made in of(*(v[at[row] : at[row + 1]] for at, v in columns)):
                    kept.append(made)
                    size += len(made[0])
                    if size >= PAIRS:
                        yield _summed(kept)
                        kept, size = [], 0
        if size:
            yield _summed(kept)

    return run


def _summed(made: list[tuple[np.ndarray, ...]]) -> pa.RecordBatch:
    """Pairs with equal ones united."""
    x, y, p, q, w = (np.concatenate(c) for c in zip(*made, strict=True))
    order = np.lexsort((y, x))
    x, y = x[order], y[order]
    first = np.flatnonzero(np.concatenate([[True], (x[1:] != x[:-1]) | (y[1:] != y[:-1])]))
    return pa.RecordBatch.from_arrays([pa.array(v) for v in (x[first], y[first], p[order][first], q[order][first], np.add.reduceat(w[order], first))], names=["x", "y", "p", "q", "w"])


def _connected(edges: DataFrame, max_rounds: int) -> DataFrame:
    """(part, least): for each end of an edge (p, q) the least one it is connected with, by rounds of least-label
    propagation, which also follow the label of a label, until none moves."""
    both = edges.unionByName(edges.select(F.col("p").alias("q"), F.col("q").alias("p")))
    label = written(both.groupBy(F.col("p").alias("part")).agg(F.least("p", F.min("q")).alias("least")))
    for _ in range(max_rounds):
        near = both.join(label.select(F.col("part").alias("q"), F.col("least").alias("c")), "q").groupBy(F.col("p").alias("part")).agg(F.min("c").alias("c"))
        up = label.select(F.col("part").alias("least"), F.col("least").alias("above"))
        moved = written(label.join(near, "part").join(up, "least").select("part", F.least("least", "c", "above").alias("least"), F.col("least").alias("was")))
        label = moved.select("part", "least")
        if not moved.filter("least <> was").limit(1).count():
            return label
    raise RuntimeError("communities did not settle; raise max_rounds")


def community_update(before: DataFrame, after: DataFrame) -> DataFrame:
    """Communities whose members changed: the region an append touches follows derived structure."""
    return L.diff(before, after, ["entity", "community"]).filter("change <> 'kept'").select("community").distinct()


def full_chart(nodes: DataFrame, anchors: DataFrame) -> DataFrame:
    return anchors.join(nodes, "scope").groupBy("anchor").agg(F.count("*").alias("n_nodes"), F.sum("tokens").alias("tokens_used"))


def recent_k(nodes: DataFrame, k: int) -> DataFrame:
    """The latest k of each scope; what is older is dropped without a word."""
    w = Window.partitionBy("scope").orderBy(F.desc("us"), F.desc("node"))
    return nodes.withColumn("r", F.row_number().over(w)).filter(F.col("r") <= k).drop("r")


def bundle_serialization(items: DataFrame) -> DataFrame:
    """One exchange bundle text per scope."""
    g = items.groupBy("scope").agg(F.sort_array(F.collect_list(F.struct("node", "kind", "us"))).alias("entry"))
    return g.select("scope", F.to_json(F.struct("entry")).alias("bundle"))


def rebuild_all(tags: DataFrame, rule: L.LinkRule, mode: str = "both") -> DataFrame:
    return L.derive(tags, rule, mode)


def incident_only(tags: DataFrame, new: DataFrame, rule: L.LinkRule, mode: str) -> tuple[DataFrame, DataFrame]:
    """(exact, patched): the full link set after an append, and the one patched with only pairs that touch
    a new node, capped among what is there; caps make the patch wrong."""
    old_tags = tags.join(new, "node", "left_anti")
    keep = L.cap(L.score(L.candidates(old_tags, rule), rule), rule.cap, mode)
    scored = L.score(L.candidates(tags, rule), rule)
    n = new.select("node")
    fresh = scored.join(n.withColumnRenamed("node", "src"), "src", "left_semi").unionByName(scored.join(n.withColumnRenamed("node", "dst"), "dst", "left_semi")).dropDuplicates(["scope", "src", "dst"])
    return L.cap(scored, rule.cap, mode), keep.select(scored.columns).unionByName(L.cap(fresh, rule.cap, mode).select(scored.columns))


def unordered_cap(scored: DataFrame, k: int, seed: int) -> DataFrame:
    """A cap that takes pairs as some hash order brings them."""
    return L.cap(scored.withColumn("score", F.xxhash64(F.lit(seed), "src", "dst")), k, "source")


def sync_migration(store, tags: DataFrame, scopes: DataFrame, rules: list[L.LinkRule], target: str) -> None:
    """Stop-the-world: all scopes in one transaction; no reader sees the target before the last is done."""
    from evigraph.plans import projection

    projection.project_scopes(store, tags, scopes.select("scope", "watermark"), rules, target)


def transactions(store) -> DataFrame:
    """(transactions, largest): how many publications a store saw, and the scopes that the largest held."""
    return store.history().groupBy("attempt").agg(F.count("*").alias("n")).agg(F.count("*").alias("transactions"), F.max("n").alias("largest"))


def materialized_queue(scopes: DataFrame, target: str) -> DataFrame:
    """A queue that copies every scope up front, where the backlog is a filter and copies none."""
    return written(scopes.select("scope", F.lit(target).alias("target"), F.lit("waiting").alias("state")))


def community_reports(mentions: DataFrame, communities: DataFrame, words: int = 5) -> DataFrame:
    """(community, entities, documents, report): a line for each community, its commonest entities first."""
    of = mentions.join(communities, "entity")
    n = of.groupBy("community", "entity").agg(F.count_distinct("doc_id").alias("docs"))
    top = n.withColumn("r", F.row_number().over(Window.partitionBy("community").orderBy(F.desc("docs"), "entity"))).filter(F.col("r") <= words)
    text = top.groupBy("community").agg(F.array_join(F.transform(F.sort_array(F.collect_list(F.struct("r", "entity", "docs"))), lambda x: F.format_string("%s (%d)", x["entity"], x["docs"])), ", ").alias("report"))
    size = of.groupBy("community").agg(F.count_distinct("entity").alias("entities"), F.count_distinct("doc_id").alias("documents"))
    return size.join(text, "community")


def last_rule_wins(links: DataFrame) -> DataFrame:
    """Without the rule in the key one assertion overwrites another."""
    return links.groupBy("scope", "src", "dst", "relation").agg(F.max("rule_id").alias("rule_id"))


def frozen_links(old: DataFrame, new: DataFrame) -> DataFrame:
    """Links made immutable at one generation: those the next one no longer asserts are stale."""
    return L.diff(old, new, ["scope", "src", "dst"]).groupBy("change").agg(F.count("*").alias("n"))


def no_status(links: DataFrame, status: DataFrame) -> DataFrame:
    """How many links serve a withdrawn or superseded end if status is not looked at."""
    s = status.select("node", "status")
    j = links.join(s.select(F.col("node").alias("src"), F.col("status").alias("ss")), "src").join(s.select(F.col("node").alias("dst"), F.col("status").alias("ds")), "dst")
    return j.agg(F.count("*").alias("links"), F.sum(((F.col("ss") == "retracted") | (F.col("ds") == "retracted")).cast("long")).alias("retracted_served"), F.sum(((F.col("ss") == "superseded") | (F.col("ds") == "superseded")).cast("long")).alias("superseded_served"))


def silent_budget(sized: DataFrame, tokens: int) -> DataFrame:
    """Cut at the budget and tell nothing."""
    w = Window.partitionBy("anchor").orderBy("ord").rowsBetween(Window.unboundedPreceding, 0)
    return sized.withColumn("used", F.sum("tokens").over(w)).filter(F.col("used") <= tokens)


def layout_stats(frames: DataFrame, per_file: int) -> DataFrame:
    """Files of one-object-a-file against packs of scopes."""
    return frames.agg(F.count("*").alias("object_files"), F.count_distinct("scope_root").alias("scopes"), F.sum("frame_len").alias("chars")).withColumn("pack_files", F.ceil(F.col("object_files") / per_file))


def one_file_per_object(frames: DataFrame, path: str) -> DataFrame:
    """Write each object to a file of its own, and read back what that makes: (files, bytes, objects)."""
    frames.withColumn("object", F.col("capsule_id")).write.partitionBy("object").parquet(path)
    return laid_out(frames.sparkSession.read.parquet(path))


def laid_out(stored: DataFrame) -> DataFrame:
    """(files, bytes, objects) of a stored table."""
    per = stored.select(F.col("_metadata.file_path").alias("file"), F.col("_metadata.file_size").alias("size"), "capsule_id").groupBy("file").agg(F.max("size").alias("size"), F.count("*").alias("n"))
    return per.agg(F.count("*").alias("files"), F.sum("size").alias("bytes"), F.sum("n").alias("objects"))


def unscoped_links(tags: DataFrame, rule: L.LinkRule) -> DataFrame:
    """Matching without the scope: how many pairs there would be, and how many would cross scopes. Pairs are
    counted, not made: those that cross are those of known scopes less those within a scope."""
    t = tags.filter(F.col("ns").isin(*rule.namespaces) & F.col("code").isNotNull() & F.col("us").isNotNull())
    of = t.groupBy("code", "scope", "us").agg(F.count("*").alias("n"))
    of = written(of.select("code", "scope", "us", "n", F.when(F.col("scope").isNotNull(), F.col("n")).otherwise(0).alias("known")))
    window = rule.window_us or 0
    every = _pairs_within(of.groupBy("code", "us").agg(F.sum("n").alias("n"), F.sum("known").alias("known")), ["code"], window, ["n", "known"])
    own = _pairs_within(of.filter("scope is not null").select("code", "scope", "us", "n"), ["code", "scope"], window, ["n"])
    return every.crossJoin(own.withColumnRenamed("n", "own")).select(F.col("n").alias("pairs"), (F.col("known") - F.col("own")).alias("cross_scope"))


def _pairs_within(at: DataFrame, keys: list[str], window: int, weights: list[str]) -> DataFrame:
    """One row: pairs of a later and an earlier time of the same keys that are at most ``window`` apart, for each
    of the weights of a time (keys, us). Time is dealt in spans of the window's length; each time meets
    those before it in its span, and asks the next span how many lie up to its own end, so both are one
    running sum."""
    span = F.floor(F.col("us") / F.lit(max(window, 1))).cast("long")
    moved = [F.struct(span.alias("span"), F.col("us").alias("at"), F.lit(False).alias("asks"))]
    if window:
        moved.append(F.struct((span + 1).alias("span"), (F.col("us") + window).alias("at"), F.lit(True).alias("asks")))
    rows = at.withColumn("m", F.explode(F.array(*moved))).select(*keys, *weights, "m.*")
    w = Window.partitionBy(*keys, "span").orderBy("at", "asks").rowsBetween(Window.unboundedPreceding, 0)
    before = lambda c: F.sum(F.when(~F.col("asks"), F.col(c)).otherwise(0)).over(w) - F.when(F.col("asks"), 0).otherwise(F.col(c))
    met = rows.select("asks", *weights, *(before(c).alias(f"{c}_met") for c in weights))
    zero = F.lit(0).cast("long")
    return met.agg(*(F.coalesce(F.sum(F.col(c) * F.col(f"{c}_met")), zero).alias(c) for c in weights))
