"""Governed links: rules, candidates, scores, caps, ids, the escalation gate."""

from __future__ import annotations

from dataclasses import asdict, dataclass, field

import pandas as pd
from pyspark.sql import Column, DataFrame, SparkSession, Window
from pyspark.sql import functions as F

from evigraph.functions.canonical import canonical_text

SEVERITY = {"info": 0, "warning": 1, "critical": 2}
BASIS = {"co-occurrence": 0, "proposed": 0, "curated": 1, "guideline": 2}


@dataclass(frozen=True)
class LinkRule:
    name: str
    relation: str
    namespaces: tuple[str, ...]
    window_us: int | None
    cap: int
    kinds: tuple[str, ...] = ()
    min_shared: int = 1
    frequency: tuple[int, int] = (1, 1 << 40)
    min_gap_us: int = 0
    severity: str = "info"
    basis: str = "co-occurrence"
    author: str = "engine"
    revision: int = 1
    valid_us: tuple[int, int] = (0, 1 << 62)
    evidence: tuple[str, ...] = ()
    weights: dict = field(default_factory=dict)

    def body(self) -> str:
        import json

        return canonical_text(json.dumps(asdict(self)))

    def rule_id(self) -> str:
        """A rule is content: a revision is another id."""
        import hashlib

        return hashlib.sha256(self.body().encode()).hexdigest()


DAY_US = 86_400_000_000
R1 = LinkRule("R1", "co_occurs", ("etype",), 7 * DAY_US, 3)
R2 = LinkRule("R1", "co_occurs", ("etype",), 3 * DAY_US, 2, revision=2)
R3 = LinkRule("R3", "continues", ("brand", "class"), 180 * DAY_US, 4, min_shared=2)
R4 = LinkRule("R4", "relevant_to", ("part",), None, 1 << 30, severity="warning", basis="curated", author="curator")
R5 = LinkRule("R5", "relevant_to", ("part",), None, 1 << 30, severity="warning", basis="curated", author="curator")
R6 = LinkRule("R6", "continues", ("brand", "class"), 180 * DAY_US, 4, min_shared=2, author="rival")
PRESETS = {"cooccur": R1, "continuation": R3, "relevance": R4, "guideline": LinkRule("G1", "guided_by", ("part",), None, 1, severity="warning", basis="guideline")}


def rule_capsules(spark: SparkSession, rules: list[LinkRule]) -> DataFrame:
    return spark.createDataFrame([(r.rule_id(), r.name, r.revision, r.body()) for r in rules], "rule_id string, name string, revision int, body string")


def applicable(rules: list[LinkRule], at_us: int) -> list[LinkRule]:
    return [r for r in rules if r.valid_us[0] <= at_us < r.valid_us[1]]


def tag_frequency(tags: DataFrame) -> DataFrame:
    return tags.groupBy("scope", "ns", "code").agg(F.count("*").alias("f"))


def bound_tags(tags: DataFrame, low: int, high: int) -> DataFrame:
    """Tags within the rule's frequency bounds of their scope, before any pair is made."""
    w = Window.partitionBy("scope", "ns", "code")
    return tags.withColumn("f", F.count("*").over(w)).filter(F.col("f").between(low, high))


def within(gap: Column, rule: LinkRule) -> Column:
    ok = gap >= rule.min_gap_us
    return ok if rule.window_us is None else ok & (gap <= rule.window_us)


def neighboured(nodes: DataFrame, keys: list[str], at: str, most: int) -> DataFrame:
    """Rows with another row of the same keys no further off in ``at`` than ``most``: whatever is in a pair that
    shares all the keys is among them, and few others, so ids and tags are needed of these only."""
    w = Window.partitionBy(*keys).orderBy(at)
    near = lambda c: F.coalesce(F.abs(F.col(at) - c) <= most, F.lit(False))
    known = nodes.filter(" and ".join(f"{c} is not null" for c in (*keys, at)))
    return known.withColumns({"_a": F.lag(at).over(w), "_b": F.lead(at).over(w)}).filter(near(F.col("_a")) | near(F.col("_b"))).drop("_a", "_b")


def candidates(tags: DataFrame, rule: LinkRule, bound: bool = True) -> DataFrame:
    """Pairs of nodes of one scope that share enough tags: src is the earlier by (us, node). Where the rule
    has a window, a node meets only those of its own span of time, as long as the window, and of the
    next one, so a busy scope costs its neighbours in time and not its square, and spans are dealt to
    tasks apart."""
    t = tags.filter(F.col("ns").isin(*rule.namespaces))
    if rule.kinds and "kind" in tags.columns:
        t = t.filter(F.col("kind").isin(*rule.kinds))
    if bound and rule.frequency != (1, 1 << 40):
        t = bound_tags(t, *rule.frequency)
    a = t.select("scope", "ns", "code", F.col("node").alias("src"), F.col("us").alias("src_us"), F.col("k").alias("src_k"))
    b = t.select("scope", "ns", "code", F.col("node").alias("dst"), F.col("us").alias("dst_us"), F.col("k").alias("dst_k"))
    keys = ["scope", "ns", "code"]
    if rule.window_us:
        span = lambda c: F.floor(F.col(c) / F.lit(rule.window_us)).cast("long")
        a = a.withColumn("span", F.explode(F.array(span("src_us"), span("src_us") + 1)))
        b = b.withColumn("span", span("dst_us"))
        keys.append("span")
    # by shuffle: a table's size on disk says little of its rows, so the engine may not choose to broadcast
    pairs = a.join(b.hint("merge"), keys).filter(F.struct("src_us", "src") < F.struct("dst_us", "dst")).drop("span")
    pairs = pairs.filter(within(F.col("dst_us") - F.col("src_us"), rule))
    if rule.min_shared == 1 and len(rule.namespaces) == 1:
        return pairs.withColumn("shared", F.lit(1).cast("long")).withColumn("tag", F.concat_ws(":", "ns", "code")).drop("ns", "code")
    tag = F.concat_ws(":", "ns", "code")
    one = pairs.groupBy("scope", "src", "dst", "src_us", "dst_us", "src_k", "dst_k").agg(F.count_distinct(tag).alias("shared"), F.min(tag).alias("tag"))
    return one.filter(F.col("shared") >= rule.min_shared)


def score(cands: DataFrame, rule: LinkRule) -> DataFrame:
    """Integer score from parts that are all ints; a rule's own weights go before the preset ones."""
    gap = F.col("dst_us") - F.col("src_us")
    far = F.expr(f"(100 * (dst_us - src_us)) div {rule.window_us}") if rule.window_us else F.least(F.lit(100), F.expr(f"(dst_us - src_us) div {30 * DAY_US}"))
    recency = F.lit(100) - far
    closeness = F.lit(100) - F.abs(F.col("src_k") - F.col("dst_k"))
    if rule.weights:
        parts = {"shared": F.col("shared"), "recency": recency, "closeness": closeness}
        value = sum((parts[k] * int(w) for k, w in sorted(rule.weights.items())), F.lit(0))
    elif rule.min_shared > 1:
        value = F.col("shared") * 50 + recency
    elif rule.window_us:
        value = closeness * 10 + recency
    else:
        value = recency
    return cands.withColumn("score", value.cast("long")).withColumn("gap_us", gap)


def ranks(links: DataFrame) -> DataFrame:
    """Severity and basis as numbers, the higher the sooner a link is taken."""
    of = lambda c, known: F.coalesce(F.create_map(*(F.lit(x) for kv in known.items() for x in kv))[F.col(c)], F.lit(0))
    return links.withColumns({"rank_severity": of("severity", SEVERITY), "rank_basis": of("basis", BASIS)})


def order(several_rules: bool = False) -> list[Column]:
    """The complete total order: severity, basis and score down, then the keys up. Within one rule severity
    and basis are equal, so score and keys are left."""
    within_rule = [F.desc("score"), F.asc("src"), F.asc("dst")]
    return [F.desc("rank_severity"), F.desc("rank_basis"), *within_rule, F.asc("relation"), F.asc("rule_id")] if several_rules else within_rule


def _order() -> list[Column]:
    return order()


def cap(scored: DataFrame, k: int, mode: str = "both") -> DataFrame:
    """Keep pairs by their rank at the source, at both ends, at either end, or greedily in order."""
    if mode == "greedy":
        return greedy(scored, k)
    ws = Window.partitionBy("scope", "node").orderBy(*_order())
    ends = scored.withColumn("node", F.explode(F.array("src", "dst"))).withColumn("r", F.row_number().over(ws)).filter(F.col("r") <= k)
    if mode == "source":  # among all pairs at the source, also those that come to it
        return ends.filter(F.col("node") == F.col("src")).drop("r", "node").select(scored.columns)
    n = ends.groupBy("scope", "src", "dst").agg(F.count("*").alias("n")).filter(F.col("n") >= (2 if mode == "both" else 1))
    return scored.join(n.drop("n"), ["scope", "src", "dst"], "left_semi")


def greedy(scored: DataFrame, k: int) -> DataFrame:
    """Scan each scope's pairs in order; keep a pair while both ends have room."""
    def run(pdf: pd.DataFrame) -> pd.DataFrame:
        pdf = pdf.sort_values(["score", "src", "dst"], ascending=[False, True, True])
        used: dict = {}
        keep = []
        for s, d in zip(pdf["src"], pdf["dst"], strict=True):
            ok = used.get(s, 0) < k and used.get(d, 0) < k
            keep.append(ok)
            if ok:
                used[s], used[d] = used.get(s, 0) + 1, used.get(d, 0) + 1
        return pdf[keep]

    return scored.groupBy("scope").applyInPandas(run, scored.schema)


def greedy_rounds(scored: DataFrame, k: int) -> DataFrame:
    """The same set for scopes too large for one task: in each round every pair that is the best left
    at both its ends is taken, and ends that are full take their pairs out, until no pair is left."""
    from evigraph.plans.store import written

    left, kept, more = written(scored), None, None
    while more != 0:
        ends = left.withColumn("node", F.explode(F.array("src", "dst")))
        used = (kept.withColumn("node", F.explode(F.array("src", "dst"))).groupBy("scope", "node").agg(F.count("*").alias("u")) if kept is not None else ends.groupBy("scope", "node").agg(F.lit(0).cast("long").alias("u")))
        r = ends.withColumn("r", F.row_number().over(Window.partitionBy("scope", "node").orderBy(*_order()))).join(used, ["scope", "node"], "left")
        room = r.withColumn("ok", F.col("r") <= F.lit(k) - F.coalesce("u", F.lit(0)))
        take = room.groupBy("scope", "src", "dst").agg(F.min("ok").alias("ok")).filter("ok").drop("ok")
        taken = left.join(take, ["scope", "src", "dst"], "left_semi")
        kept = written(taken if kept is None else kept.unionByName(taken))
        full = kept.withColumn("node", F.explode(F.array("src", "dst"))).groupBy("scope", "node").agg(F.count("*").alias("u")).filter(F.col("u") >= k).select("scope", "node")
        left = left.join(take, ["scope", "src", "dst"], "left_anti")
        left = left.join(full.withColumnRenamed("node", "src"), ["scope", "src"], "left_anti").join(full.withColumnRenamed("node", "dst"), ["scope", "dst"], "left_anti")
        left = written(left.select(scored.columns))
        was, more = more, left.count()
        if more and more == was:
            raise RuntimeError("a round took no pair; pairs must differ in (scope, src, dst)")
    return kept


def identify(kept: DataFrame, rule: LinkRule, run_id: str = "", rule_id: str | None = None) -> DataFrame:
    """Link ids and times from immutable inputs; the run is named beside them, never in them."""
    rid = rule_id or rule.rule_id()
    key = F.concat_ws("|", F.col("src").cast("string"), F.col("dst").cast("string"), F.lit(rule.relation), "tag", F.lit(rid))
    return kept.select(
        F.sha2(key, 256).alias("link_id"), "scope", "src", "dst", F.lit(rule.relation).alias("relation"), "tag", F.lit(rule.severity).alias("severity"), F.lit(rule.basis).alias("basis"),
        F.lit(rid).alias("rule_id"), "score", F.greatest("src_us", "dst_us").alias("link_us"), F.lit(run_id).alias("run_id"),
    )


def derive(tags: DataFrame, rule: LinkRule, mode: str = "both", run_id: str = "", rule_id: str | None = None) -> DataFrame:
    return identify(cap(score(candidates(tags, rule), rule), rule.cap, mode), rule, run_id, rule_id)


def project(tags: DataFrame, rules: list[LinkRule], run_id: str, mode: str = "both") -> DataFrame:
    """All rules of a release over one set of tags; assertions of different rules stay side by side."""
    out = derive(tags, rules[0], mode, run_id)
    for r in rules[1:]:
        out = out.unionByName(derive(tags, r, mode, run_id))
    return out.dropDuplicates(["link_id"])


def consolidate(links: DataFrame) -> DataFrame:
    """One row per pair and relation for display: the highest severity and score, and every rule that
    asserts it with what it rests on."""
    severity = F.create_map(*(F.lit(x) for kv in SEVERITY.items() for x in kv))[F.col("severity")]
    path = F.struct("rule_id", "severity", "basis", "tag", "score")
    return links.groupBy("scope", "src", "dst", "relation").agg(
        F.count_distinct("rule_id").alias("n_rules"), F.max("score").alias("score"), F.max_by("severity", severity).alias("severity"), F.array_join(F.array_sort(F.collect_set("rule_id")), ",").alias("rules"), F.array_sort(F.collect_set(path)).alias("paths"))


def escalation_gate(links: DataFrame, evidence: DataFrame) -> tuple[DataFrame, DataFrame]:
    """(accepted, rejected with reason): above info a link needs a curated or guideline basis, a rule and
    evidence that resolves; proposals stay at info."""
    known = evidence.select(F.col("evidence_id"), F.lit(True).alias("resolves")).distinct()
    j = links.join(known, "evidence_id", "left")
    above = F.col("severity") != "info"
    reason = (
        F.when(above & ~F.col("basis").isin("curated", "guideline"), "basis").when(above & (F.col("rule_id").isNull() | (F.col("rule_id") == "")), "rule")
        .when(above & F.col("resolves").isNull(), "evidence")
    )
    j = j.withColumn("reason", reason).drop("resolves")
    return j.filter("reason is null").drop("reason"), j.filter("reason is not null")


def propose(pairs: DataFrame, rule_id: str) -> DataFrame:
    """Learned or vector proposals enter as info-level candidates only."""
    return pairs.withColumns({"severity": F.lit("info"), "basis": F.lit("proposed"), "rule_id": F.lit(rule_id)})


def diff(old: DataFrame, new: DataFrame, keys: list[str]) -> DataFrame:
    """Keys with change: added, removed or kept."""
    a, b = old.select(*keys, F.lit(True).alias("o")), new.select(*keys, F.lit(True).alias("n"))
    j = a.join(b, keys, "full_outer")
    return j.select(*keys, F.when(F.col("o").isNull(), "added").when(F.col("n").isNull(), "removed").otherwise("kept").alias("change"))
