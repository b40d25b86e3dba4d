"""N-gram Jaccard join by a token-group matrix.

Documents with equal shingle sets form one class. Classes that share a prefix token are first tied to
one leader each at a cost linear in the postings; those that meet the threshold are tied. Classes that
share a least leader are a group of similar classes, linked or not, cut into blocks of bounded size; a
block's row of the matrix is the union of its members' tokens. A class is then held against every
block with which it shares a prefix token: only where its overlap with the block's token union reaches
the least overlap any partner must have is the block opened and its members compared, but for those
tied to the class already.

Prefix filter: with a total order of tokens, two sets of Jaccard similarity t or more share a token
among the first n - ceil(t n) + 1 of each, ``SHARED`` tokens among SHARED - 1 more (more still if their
sizes are alike), and the first one they share leaves enough of both behind it. Long shingles come first in the order and frequent ones (counted over the whole corpus in buckets
of token hashes) last, so common words and lines do not make candidates. The order only affects
cost; every pair of classes at or above the threshold ends up in one component.

Defined results: null, empty or blank text has no shingles, no links and is its own component; rows
that repeat a doc_id are judged each by their own text; a null doc_id gets the component of its text,
or null where no row of it has an id; further columns are ignored.
"""

from __future__ import annotations

import zlib
from collections.abc import Iterator

import numpy as np
import pyarrow as pa
import xxhash
from pyspark.sql import DataFrame, Window
from pyspark.sql import functions as F

from evigraph.llm import common, text

#: Buckets in which token frequencies are counted, how many of them may count as frequent, and the
#: most members of a block of the matrix.
BUCKETS, FREQUENT, BLOCK = 1 << 22, 100_000, 64
#: Prefix tokens that must agree, and the bits of the filter that spares the reading of other documents.
SHARED, FILTER_BITS = 3, 1 << 24
#: Large groups, and blocks that many classes ask, whose sizes are broadcast at most (more are joined by
#: shuffle), and classes that ask a block in one task.
GROUPS, QUERIES = 100_000, 256


def _sets(part: pa.RecordBatch, size: int) -> list[np.ndarray]:
    w = text.words(*common.raw(part.column("text")), text.SPACED)
    s, bounds = text.shingles(w, size)
    s = text.rare_first(s, w, size)
    return [np.unique(s[a:b]) for a, b in zip(bounds[:-1], bounds[1:], strict=True)]


def _fingerprints(sets: list[np.ndarray]) -> pa.Array:
    return pa.array([xxhash.xxh3_128_digest(s.tobytes()) if len(s) else None for s in sets], pa.binary())


def frequency_levels(docs: DataFrame, size: int) -> np.ndarray:
    """A level for each bucket of token hashes: 0, or for those that most documents hold a number
    that grows with the logarithm of their count. Each task reports the buckets that stand out."""

    def count(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        total = np.zeros(BUCKETS, np.int32)
        for batch in batches:
            for part in common.slices(batch, "text"):
                sets = _sets(part, size)
                if sets:
                    total += np.bincount((np.concatenate(sets) & np.uint64(BUCKETS - 1)).astype(np.int64), minlength=BUCKETS).astype(np.int32)
        mean = total.mean()
        high = np.flatnonzero(total >= max(4, mean + 6 * np.sqrt(mean) + 2))
        if len(high) > FREQUENT // 4:
            high = high[np.argpartition(total[high], -(FREQUENT // 4))[-(FREQUENT // 4) :]]
        yield pa.RecordBatch.from_arrays([pa.array(high.astype(np.int64)), pa.array(total[high].astype(np.int64))], names=["bucket", "n"])

    top = common.written(docs.select("text").mapInArrow(count, "bucket long, n long").groupBy("bucket").agg(F.sum("n").alias("n")))
    top = top.withColumn("level", F.least(F.lit(255), 1 + F.floor(8 * F.log2(F.col("n").cast("double")))).cast("int"))
    # the levels that at most FREQUENT buckets reach; the rest of the table stays where it is
    least, seen = 256, 0
    for r in sorted(top.groupBy("level").agg(F.count("*").alias("c")).collect(), reverse=True):
        seen += r["c"]
        if seen > FREQUENT:
            break
        least = r["level"]
    levels = np.zeros(BUCKETS, np.uint8)
    for r in top.filter(F.col("level") >= least).select("bucket", "level").collect():
        levels[r["bucket"]] = r["level"]
    return levels


def _least(n, num: int, den: int):
    return (n * num + den - 1) // den


def signatures(docs: DataFrame, size: int, num: int, den: int) -> DataFrame:
    """doc_id, n (set size), class (128-bit fingerprint of the set; null without words), prefix."""
    packed = zlib.compress(frequency_levels(docs, size).tobytes(), 1)

    def sign(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        levels = np.frombuffer(zlib.decompress(packed), np.uint8)
        for batch in batches:
            for part in common.slices(batch, "text"):
                sets = _sets(part, size)
                prefixes = []
                for s in sets:
                    n = len(s)
                    k = n - _least(n, num, den) + SHARED if n * den >= (n + 1) * num else 0  # else no other set is close enough
                    if not n or not k:
                        prefixes.append(s[:0].view(np.int64))
                        continue
                    prefixes.append(s[np.argsort(levels[(s & np.uint64(BUCKETS - 1)).astype(np.int64)], kind="stable")[:k]].view(np.int64))
                yield pa.RecordBatch.from_arrays([
                    part.column("doc_id"), pa.array([len(s) for s in sets], pa.int64()),
                    _fingerprints(sets), pa.array(prefixes, pa.list_(pa.int64())),
                ], names=["doc_id", "n", "class", "prefix"])

    kind = dict(docs.dtypes)["doc_id"]
    return docs.select("doc_id", "text").mapInArrow(sign, f"doc_id {kind}, n long, class binary, prefix array<long>")


def token_sets(docs: DataFrame, wanted: DataFrame, size: int) -> DataFrame:
    """(id, tokens) of the classes in ``wanted`` (id, class, doc_id). A filter of fixed size on the ids
    spares most other documents; a join drops the rest, so texts are never shuffled."""
    word = F.pmod(F.xxhash64("doc_id"), F.lit(FILTER_BITS))
    bits = wanted.select(F.shiftright(word, 6).alias("k"), F.expr(f"shiftleft(1L, cast(pmod(xxhash64(doc_id), {FILTER_BITS}) & 63 as int))").alias("b")).groupBy("k").agg(F.bit_or("b").alias("b")).toPandas()
    filled = np.zeros(FILTER_BITS // 64, np.int64)
    filled[bits["k"].to_numpy(np.int64)] = bits["b"].to_numpy(np.int64)
    packed = zlib.compress(filled.tobytes(), 1)

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        filled = np.frombuffer(zlib.decompress(packed), np.uint64)
        for batch in batches:
            for part in common.slices(batch, "text"):
                at = part.column("at").to_numpy(zero_copy_only=False)
                may = np.flatnonzero((filled[at >> 6] >> (at & 63).astype(np.uint64)) & np.uint64(1))
                if not len(may):
                    continue
                part = part.take(pa.array(may))
                sets = _sets(part, size)
                yield pa.RecordBatch.from_arrays([_fingerprints(sets), pa.array([s.view(np.int64) for s in sets], pa.list_(pa.int64()))], names=["class", "tokens"])

    some = docs.select("text", word.alias("at")).mapInArrow(run, "class binary, tokens array<long>")
    return some.join(wanted, "class").groupBy("id").agg(F.first("tokens").alias("tokens"))


def _reach(n, at, least, at_least, most, num: int, den: int):
    """Whether a set of ``n`` tokens with the shared token at place ``at`` and sets of ``least`` to
    ``most`` tokens with it at ``at_least`` or later can still overlap enough."""
    need = F.ceil((n + least) * num / (num + den)).cast("long")
    return (n - at >= need) & (most - at_least >= need) & (most * den >= n * num) & (n * den >= least * num)


def _need(n, least, most, num: int, den: int):
    """Prefix tokens that a set of ``n`` must share with one of ``least`` to ``most`` tokens. Of two
    prefixes, all tokens of the one that ends first in the order that are in the other set are in its
    prefix too, and only n - overlap of its tokens may be missing there."""
    low = F.greatest(least, F.ceil(n * num / den))
    high = F.least(most, F.floor(n * den / num))
    both = lambda m: F.ceil((n + m) * num / (num + den))
    first = F.lit(SHARED) - F.ceil(n * num / den) + both(low)
    second = F.lit(SHARED - 1) - F.ceil(high * num / den) + both(high)  # 1 less for the rounding
    return F.greatest(F.lit(1), F.least(first, second))


def _linked(pairs: DataFrame, sets: DataFrame, num: int, den: int) -> DataFrame:
    """The pairs (a, b) of classes that meet the threshold exactly."""
    left = pairs.join(sets.select(F.col("id").alias("b"), F.col("tokens").alias("tb")), "b")
    both = left.join(sets.select(F.col("id").alias("a"), F.col("tokens").alias("ta")), "a")
    both = both.select("a", "b", F.size(F.array_intersect("ta", "tb")).cast("long").alias("i"), (F.size("ta") + F.size("tb")).cast("long").alias("s"))
    return both.filter(F.col("i") * den >= (F.col("s") - F.col("i")) * num).select("a", "b")


def join(docs: DataFrame, size: int = 3, num: int = 90, den: int = 100) -> DataFrame:
    """doc_id, n_shingles, component_id of every row: documents link when den * intersection >= num *
    union of their sets of ``size``-word shingles; a component's id is its smallest doc_id."""
    signed = common.written(signatures(docs, size, num, den))
    classes = signed.filter("class is not null").groupBy("class").agg(F.min("doc_id").alias("doc_id"), F.first("n").alias("n"))
    # a class is numbered by its least doc_id; where that is null or leads several classes, by a hash
    twice = classes.groupBy("doc_id").agg(F.count("*").alias("c")).filter("c > 1").select("doc_id", F.lit(True).alias("clash"))
    number = F.when(F.col("doc_id").cast("long").isNull() | F.col("clash").isNotNull(), -F.abs(F.xxhash64("class")) - 1).otherwise(F.col("doc_id").cast("long"))
    classes = common.written(classes.join(twice, "doc_id", "left").select("class", "doc_id", number.alias("id"), "n"))

    led = signed.filter(F.size("prefix") > 0).select("class", "doc_id", "prefix").join(classes, "class").filter(signed["doc_id"].eqNullSafe(classes["doc_id"]))
    postings = led.groupBy("id").agg(F.first("n").cast("int").alias("n"), F.first("prefix").alias("prefix")).select("id", "n", F.posexplode("prefix").alias("at", "token"))
    # tokens of one class alone lead nowhere; a band holds sizes of which the smaller can reach the larger's share
    whole = Window.partitionBy("token")
    postings = postings.withColumns({"lo": F.min("id").over(whole), "hi": F.max("id").over(whole)}).filter("lo <> hi").drop("lo", "hi")
    band = F.floor(F.log(F.col("n").cast("double")) / F.log(F.lit(den / num))).cast("int")
    postings = common.written(postings.withColumn("band", band))

    leaders = postings.groupBy("token", "band").agg(F.min(F.struct("id", "n", "at")).alias("l"))
    meets = _reach(F.col("n"), F.col("at"), F.col("l.n"), F.col("l.at"), F.col("l.n"), num, den)
    stars = (
        postings.join(leaders, ["token", "band"]).filter(F.col("l.id") != F.col("id")).groupBy(F.col("l.id").alias("a"), F.col("id").alias("b"), F.col("l.n").alias("m"), "n")
        .agg(F.bool_or(meets).alias("meets"), F.count("*").alias("shared")).filter(F.col("meets") & (F.col("shared") >= _need(F.col("n"), F.col("m"), F.col("m"), num, den))).select("a", "b")
    )
    stars = common.written(stars)

    def sets_of(ids: DataFrame) -> DataFrame:
        return token_sets(docs, classes.join(ids.distinct(), "id", "left_semi").select("id", "class", "doc_id"), size)

    found = common.written(_linked(stars, sets_of(stars.select(F.explode(F.array("a", "b")).alias("id"))), num, den))
    tied = common.components(found).select("id", F.col("component_id").alias("tie"))

    # groups: the least leader of a class's lists; blocks: bounded parts of a group
    grouped = common.written(postings.join(leaders, ["token", "band"]).groupBy("id", "n").agg(F.min("l.id").alias("grp")))
    # groups that need more than one block are few, so that a large group is not dealt to one task
    sized = grouped.groupBy("grp").agg(F.count("*").alias("m")).filter(F.col("m") > BLOCK // 2)
    part = F.pmod(F.xxhash64("id"), F.ceil(F.coalesce("m", F.lit(1)) / (BLOCK // 2)).cast("long")).cast("int")
    member = common.joined_checked(grouped, sized, ["grp"], "left", GROUPS).select("id", F.struct("grp", part.alias("part")).alias("block"))
    member = common.written(member.join(tied, "id", "left").withColumn("tie", F.coalesce("tie", "id")))

    # cells of the matrix: a class and a block whose prefixes share enough
    query = postings.join(member.select("id", "tie", F.col("block").alias("own")), "id")
    rows = query.groupBy("token", F.col("own").alias("block")).agg(
        F.min("n").alias("least"), F.max("n").alias("most"), F.min("at").alias("at_least"), F.min("tie").alias("lo"), F.max("tie").alias("hi")
    )
    row_meets = _reach(*(F.col(c) for c in ("n", "at", "least", "at_least", "most")), num, den)
    cells = (
        query.join(rows, "token").filter("(own < block or own = block) and (lo <> tie or hi <> tie)").filter((F.col("most") * den >= F.col("n") * num) & (F.col("n") * den >= F.col("least") * num))
        .groupBy("id", "n", "tie", "block").agg(F.bool_or(row_meets).alias("meets"), F.count("*").alias("shared"), F.min("least").alias("least"), F.max("most").alias("most"))
        .filter(F.col("meets") & (F.col("shared") >= _need(*(F.col(c) for c in ("n", "least", "most")), num, den))).select("id", "tie", "block")
    )
    cells = common.written(cells)
    opened = member.join(cells.select("block").distinct(), "block", "left_semi")
    sets = common.written(sets_of(cells.select("id").unionByName(opened.select("id"))))
    blocks = opened.join(sets, "id").groupBy("block").agg(F.collect_list(F.struct("tie", "tokens")).alias("members"))
    blocks = blocks.withColumn("union", F.array_distinct(F.flatten(F.col("members.tokens"))))

    def close(m):
        i = F.size(F.array_intersect(m["tokens"], F.col("tokens")))
        return (m["tie"] != F.col("tie")) & (i * den >= (F.size(m["tokens"]) + F.size("tokens") - i) * num)

    hit = F.array_distinct(F.transform(F.filter("members", close), lambda m: m["tie"]))
    # a block that many classes ask is opened in several tasks, each for a part of them
    asked = common.written(cells.groupBy("block").agg(F.count("*").alias("asked")).filter(F.col("asked") > QUERIES).select("block", F.ceil(F.col("asked") / QUERIES).cast("long").alias("turns")))
    turns = F.coalesce("turns", F.lit(1).cast("long"))
    dealt = common.joined_checked(cells, asked, ["block"], "left", GROUPS).withColumn("turn", F.pmod(F.xxhash64("id"), turns)).drop("turns")
    blocks = common.joined_checked(blocks, asked, ["block"], "left", GROUPS).withColumn("turn", F.explode(F.sequence(F.lit(0).cast("long"), turns - 1))).drop("turns")
    bound = dealt.join(sets, "id").join(blocks, ["block", "turn"]).filter(F.size(F.array_intersect("tokens", "union")) * den >= F.size("tokens") * num)
    met = bound.select(F.col("tie").alias("a"), F.explode(hit).alias("b")).distinct()
    # classes tied to each other stand for one another, so links join their ties
    links = common.written(tied.select(F.col("id").alias("a"), F.col("tie").alias("b")).unionByName(met))
    rooted = classes.join(common.components(links), "id", "left").withColumn("root", F.coalesce("component_id", "id"))
    rooted = common.written(rooted.select("class", "root", "doc_id"))
    lowest = rooted.groupBy("root").agg(F.min("doc_id").alias("component_id"))
    named = rooted.select("class", "root").join(lowest, "root").select("class", "component_id")
    return signed.select("doc_id", F.col("n").alias("n_shingles"), "class").join(named, "class", "left").select(
        "doc_id", "n_shingles", F.when(F.col("class").isNull(), F.col("doc_id")).otherwise(F.col("component_id")).alias("component_id")
    )


def one_of_each(docs: DataFrame, size: int = 5, num: int = 80, den: int = 100) -> DataFrame:
    """The rows of ``docs`` that lead their component of five-word shingles at 0.8; rows without an id
    stay, repeated rows of a leading id leave one."""
    leads = join(docs, size, num, den).filter("doc_id = component_id").select("doc_id").distinct()
    kept = docs.filter("doc_id is not null").join(leads, "doc_id", "left_semi").select(*docs.columns).dropDuplicates(["doc_id"])
    return kept.unionByName(docs.filter("doc_id is null"))


def brute(docs: list[tuple[int, str | None]], size: int = 3, num: int = 90, den: int = 100) -> dict[int, tuple[int, int]]:
    """The contract in plain Python, for tests."""
    import re

    sets = {}
    for d, s in docs:
        w = re.findall(r"[^\x20\x09-\x0D]+", re.sub("[A-Z]", lambda m: m[0].lower(), s or ""))
        sets[d] = {tuple(w[k : k + size]) for k in range(max(1, len(w) - size + 1))} if w else set()
    up = {d: d for d in sets}

    def root(d):
        while up[d] != d:
            d = up[d]
        return d

    ids = sorted(sets)
    for k, a in enumerate(ids):
        for b in ids[k + 1 :]:
            i = len(sets[a] & sets[b])
            if sets[a] and sets[b] and i * den >= (len(sets[a]) + len(sets[b]) - i) * num:
                lo, hi = sorted((root(a), root(b)))
                up[hi] = lo
    return {d: (len(sets[d]), root(d)) for d in ids}
