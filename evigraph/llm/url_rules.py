"""URL filtering by association rules.

URLs are cut into tokens (host labels and domain suffixes, path segments and their words, query keys).
Spark's FP-growth mines the token sets of labelled pages with their label for frequent combinations;
tokens that always come together are mined as one, and where a page still has more than ``WIDE``
frequent tokens the combinations are found size by size instead, as their number would double with each
token. Rules have up to ``TOKENS`` tokens, tokens mined as one counting once. Combinations that imply a label with enough support and confidence, and more surely than no tokens at all, become
rules; a rule goes where a shorter one says the same as surely, unless it is an exception to a rule of
another verdict. Rules are matched by an inverted index that holds each under the rarest of its
tokens: a page meets the rules of its own tokens only, and a rule fires if the page has all of them. A rule that fires silences those of other verdicts whose tokens are a part of its own; of
the others the best (confidence, then support, then tokens) gives the verdict; pages on which none
fires are allowed.

A list of given (host, path) rules goes before the mined ones: a rule fits its host and subdomains if
the path starts with the rule's, the longest fits best. They are matched by an equi-join on the host's
suffixes.

Of given rules that fit equally long, the one of the longer path, then of the greater text wins. Extra
columns are ignored, urls of any length are read whole.

Defined results: a null url, or one without "://", has empty host and path and no tokens; labels that
are null or contradict each other count as their worst; without labels no rules are mined and every
page is allowed but for the given rules; repeated pages get the same verdict.
"""

from __future__ import annotations

import math
from dataclasses import dataclass

from pyspark.ml.fpm import FPGrowth
from pyspark.sql import DataFrame, Window
from pyspark.sql import functions as F

from evigraph.llm import common

#: Least share of labelled pages and confidence of a rule, the lift it must pass (a verdict's share may be
#: near 1, so no more than 1 can be asked), most tokens, and rows of the index that are broadcast at most.
SUPPORT, CONFIDENCE, LIFT, TOKENS, SENT = 0.002, 0.6, 1.0, 3, 150_000
#: Least labelled pages behind a rule, whatever the share.
PAGES = 20
#: Frequent tokens of a page up to which FP-growth is asked.
WIDE = 14


@dataclass(frozen=True)
class Given:
    host: str
    path: str
    verdict: str


#: fixed values of the filter contract
GIVEN = (Given("net", "/", "block"), Given("example.net", "/en/", "allow"), Given("example.com", "/de/", "block"), Given("org", "/fr/", "allow"))


def _lower(c):
    return F.translate(c, "ABCDEFGHIJKLMNOPQRSTUVWXYZ", "abcdefghijklmnopqrstuvwxyz")


def parts(url: str = "url") -> dict:
    """host, path and query columns of a url column."""
    u = F.coalesce(F.col(url), F.lit(""))
    rest = F.when(F.instr(u, "://") > 0, F.substring(u, F.instr(u, "://") + 3, F.length(u))).otherwise("")
    return {
        "query": F.regexp_extract(rest, r"(?s)^[^?#]*\?([^#]*)", 1),
        "host": _lower(F.regexp_extract(rest, r"(?s)^([^/?#]*)", 1)),
        "path": F.regexp_extract(F.substring(rest, F.length(F.regexp_extract(rest, r"(?s)^([^/?#]*)", 1)) + 1, F.length(rest)), r"(?s)^([^?#]*)", 1),
    }


def _suffixes(host):
    labels = F.split(host, r"\.")
    return F.transform(F.sequence(F.lit(1), F.size(labels)), lambda i: F.array_join(F.slice(labels, i, F.size(labels)), "."))


def tokens(host, path, query):
    """Distinct tokens of a url, each with the kind it is of."""
    words = F.filter(F.split(F.lower(path), r"[^a-z0-9]+"), lambda w: (w != "") & ~w.rlike("^[0-9]+$"))
    keys = F.filter(F.transform(F.split(F.lower(query), "[&;]"), lambda w: F.substring_index(w, "=", 1)), lambda w: w != "")
    return F.when(host == "", F.array().cast("array<string>")).otherwise(F.array_distinct(F.concat(
        F.transform(_suffixes(host), lambda x: F.concat(F.lit("host:"), x)),
        F.transform(F.filter(F.split(host, r"[.\-]"), lambda w: w != ""), lambda w: F.concat(F.lit("label:"), w)),
        F.transform(words, lambda w: F.concat(F.lit("path:"), w)),
        F.transform(keys, lambda w: F.concat(F.lit("query:"), w)),
    )))


def _but(place: int):
    return lambda x, i: i != place


def _frequent(baskets: DataFrame, least: int, size: int) -> DataFrame:
    """(items, freq) of the combinations of up to ``size`` items in at least ``least`` of (key, items) rows,
    size by size: a combination is counted only if all its parts without one item are frequent."""
    has = common.written(baskets.select("key", F.explode("items").alias("item")))
    every = has.groupBy("item").agg(F.count("*").alias("freq")).filter(F.col("freq") >= least)
    has = common.written(has.join(every.select("item"), "item", "left_semi"))
    out = found = common.written(every.select(F.array("item").alias("items"), "freq"))
    held = has.select("key", F.array("item").alias("items"))
    for k in range(2, size + 1):
        longer = held.join(has, "key").filter(F.element_at("items", -1) < F.col("item")).select("key", F.concat("items", F.array("item")).alias("items"))
        rest = found.select(F.col("items").alias("part"))
        if k > 2:  # the part without the last item is frequent already
            for drop in range(k - 1):
                longer = longer.withColumn("part", F.filter("items", _but(drop))).join(rest, "part", "left_semi").drop("part")
        longer = common.written(longer)
        found = common.written(longer.groupBy("items").agg(F.count("*").alias("freq")).filter(F.col("freq") >= least))
        held = longer.join(found.select("items"), "items", "left_semi")
        out = out.unionByName(found)
    return out


def combinations(labelled: DataFrame, least: int, total: int, wide: int = WIDE) -> tuple[DataFrame, DataFrame]:
    """(items, freq) of the frequent combinations of labelled pages' tokens and labels, and (group, tokens):
    what each item stands for. Tokens on exactly the same pages are one item."""
    rows = common.written(labelled.withColumn("key", F.monotonically_increasing_id()))
    has = rows.select("key", F.explode("tokens").alias("token"))
    same = has.groupBy("token").agg(F.count("*").alias("n"), F.bit_xor(F.xxhash64("key")).alias("x"), F.bit_xor(F.xxhash64(F.lit("y"), "key")).alias("y")).filter(F.col("n") >= least)
    same = common.written(same.withColumn("group", F.min("token").over(Window.partitionBy("n", "x", "y"))).select("token", "group"))
    groups = same.groupBy("group").agg(F.array_sort(F.collect_list("token")).alias("tokens"))
    own = has.join(same.filter("token = group").select("token"), "token", "left_semi").groupBy("key").agg(F.array_sort(F.collect_list("token")).alias("items"))
    marked = F.concat(F.coalesce("items", F.array().cast("array<string>")), F.array(F.concat(F.lit("="), F.col("label"))))
    baskets = common.written(rows.select("key", "label").join(own, "key", "left").select("key", marked.alias("items")))
    if (baskets.agg(F.max(F.size("items"))).first()[0] or 0) > wide + 1:
        return _frequent(baskets, least, TOKENS + 1), groups
    sets = FPGrowth(itemsCol="items", minSupport=min(1.0, least / total), minConfidence=1.0).fit(baskets).freqItemsets
    return sets.filter((F.size("items") <= TOKENS + 1) & (F.col("freq") >= least)), groups


def mined(labelled: DataFrame, support: float = SUPPORT, confidence: float = CONFIDENCE, lift: float = LIFT, wide: int = WIDE) -> DataFrame:
    """Rules (rule_id, tokens, anchor, verdict, confidence, support, over) from (tokens, label) rows; ``over``
    has the ids of the rules to which one is an exception, ``anchor`` is the rarest token."""
    spark = labelled.sparkSession
    schema = "rule_id long, tokens array<string>, anchor string, verdict string, confidence double, support double, over array<long>"
    base = {r["label"]: r["n"] for r in labelled.groupBy("label").agg(F.count("*").alias("n")).collect()}
    total = sum(base.values())
    if not total or len(base) < 2:
        return spark.createDataFrame([], schema)
    sets, groups = combinations(labelled, max(PAGES, math.ceil(support * total - 1e-9)), total, wide)
    sets = common.written(sets)
    marks = F.filter("items", lambda x: x.startswith("="))
    bodies = sets.filter(F.size(marks) == 0).select(F.array_sort("items").alias("tokens"), F.col("freq").alias("all"))
    heads = sets.filter((F.size(marks) == 1) & (F.size("items") > 1)).select(
        F.array_sort(F.filter("items", lambda x: ~x.startswith("="))).alias("tokens"), F.substring(marks[0], 2, 100).alias("verdict"), F.col("freq").alias("n"))
    rules = heads.join(bodies, "tokens").withColumns({"confidence": F.col("n") / F.col("all"), "support": F.col("n") / F.lit(float(total))})
    expected = F.create_map(*(x for k, v in base.items() for x in (F.lit(k), F.lit(v / total))))
    rules = rules.filter(F.col("confidence") >= confidence).filter(F.col("confidence") > lift * expected[F.col("verdict")])
    rules = common.written(rules.withColumn("rule_id", F.abs(F.xxhash64("tokens", "verdict"))).select("rule_id", "tokens", "verdict", "confidence", "support"))
    # each rule meets the rules of a part of its tokens, of which there are few
    part = F.explode(F.transform(F.sequence(F.lit(1), F.lit((1 << TOKENS) - 2)), lambda m: F.filter("tokens", lambda x, i: F.getbit(m, i) == 1)))
    parts_of = rules.select("rule_id", "verdict", "confidence", F.size("tokens").alias("n"), part.alias("part")).filter("size(part) > 0 and size(part) < n").dropDuplicates(["rule_id", "part"])
    short = rules.select(F.col("tokens").alias("part"), F.col("rule_id").alias("id2"), F.col("verdict").alias("v2"), F.col("confidence").alias("c2"))
    same = F.col("verdict") == F.col("v2")
    met = parts_of.join(short, "part").groupBy("rule_id").agg(F.bool_or(same & (F.col("c2") >= F.col("confidence"))).alias("said"), F.collect_list(F.when(~same, F.col("id2"))).alias("over"))
    rules = rules.join(met, "rule_id", "left").withColumn("over", F.coalesce("over", F.array().cast("array<long>")))
    kept = rules.filter(~F.coalesce("said", F.lit(False)) | (F.size("over") > 0)).drop("said")
    # items stand for all tokens that come with them; the one on the fewest pages leads to the rule
    single = bodies.filter(F.size("tokens") == 1).select(F.col("tokens")[0].alias("group"), "all")
    items = kept.select("rule_id", F.explode("tokens").alias("group")).join(single, "group").join(groups.withColumnRenamed("tokens", "own"), "group")
    whole = items.groupBy("rule_id").agg(F.array_sort(F.flatten(F.collect_list("own"))).alias("tokens"), F.min(F.struct("all", "group"))["group"].alias("anchor"))
    return common.written(kept.drop("tokens").join(whole, "rule_id").select("rule_id", "tokens", "anchor", "verdict", "confidence", "support", "over"))


def fired(pages: DataFrame, rules: DataFrame, key: str, sent: int = SENT) -> DataFrame:
    """(key, verdict) of the best rule whose tokens a page has, by the index from rarest token to rule."""
    said = ("verdict", "confidence", "support", "over")
    index = rules.select("rule_id", F.size("tokens").alias("size"), F.col("tokens").alias("asked"), *said, F.col("anchor").alias("token"))
    met = common.joined_checked(pages.select(key, "tokens", F.explode("tokens").alias("token")), index, ["token"], "inner", sent)
    full = met.filter(F.size(F.array_except("asked", "tokens")) == 0)
    rank = F.struct("confidence", "support", F.negate("size").alias("less"), "rule_id", "verdict")
    all_of = full.groupBy(key).agg(F.collect_list(rank).alias("ranks"), F.flatten(F.collect_list("over")).alias("silent"))
    return all_of.select(key, F.array_max(F.filter("ranks", lambda r: ~F.array_contains("silent", r["rule_id"])))["verdict"].alias("mined"))


def judged(pages: DataFrame, labels: DataFrame, given: tuple[Given, ...] = GIVEN, sent: int = SENT, **options) -> DataFrame:
    """page_id, host, path, rule, verdict. ``labels`` (page_id, label) hold ``block`` or ``allow``."""
    spark = pages.sparkSession
    cut = pages.select("page_id", F.coalesce("url", F.lit("")).alias("url")).withColumns(parts())
    cut = cut.withColumns({"tokens": tokens(F.col("host"), F.col("path"), F.col("query")), "url_key": F.xxhash64("host", "path", "query")})
    worst = labels.filter("page_id is not null and label is not null").groupBy("page_id").agg(F.max("label").alias("label"))  # block sorts last
    labelled = common.written(cut.join(worst, "page_id").select("tokens", "label"))
    rules = mined(labelled, **options)
    urls = cut.select("url_key", "tokens").dropDuplicates(["url_key"])
    best = fired(urls, rules, "url_key", sent)
    listed = spark.createDataFrame([(g.host, g.path, g.verdict) for g in given], "rule_host string, rule_path string, given string")
    fit = (
        cut.select("url_key", "host", "path").dropDuplicates(["url_key"]).select("url_key", "path", F.explode(_suffixes(F.col("host"))).alias("rule_host"))
        .join(F.broadcast(listed), "rule_host").filter(F.col("path").startswith(F.col("rule_path")))
        .groupBy("url_key").agg(F.max(F.struct(F.length(F.concat("rule_host", "rule_path")).alias("n"), F.length("rule_path").alias("m"), F.concat("rule_host", "rule_path").alias("rule"), "given")).alias("g"))
    )
    out = cut.select("page_id", "host", "path", "url_key").join(fit, "url_key", "left").join(best, "url_key", "left")
    return out.select("page_id", "host", "path", F.col("g.rule").alias("rule"), F.coalesce("g.given", "mined", F.lit("allow")).alias("verdict"))


def labels_of(labels: DataFrame) -> DataFrame:
    """Page labels from document labels: junk and toxic ones are to block."""
    bad = (F.col("quality") == 0) | (F.col("toxic") == 1)
    return labels.select(F.col("doc_id").alias("page_id"), F.when(F.col("quality").isNull() & F.col("toxic").isNull(), None).when(F.coalesce(bad, F.col("toxic") == 1, F.col("quality") == 0), "block").otherwise("allow").alias("label"))
