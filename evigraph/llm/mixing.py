"""Iterative proportional fitting of token weights to source, language and topic marginals, then
sampling by the calibrated probabilities.

Tokens are summed per cell (source, lang, topic) on the executors. Up to ``CELLS`` cells are raked as
arrays on the driver; more are raked as a table, sweep by sweep, in the shared folder, to the same gap
and with the same limit of sweeps; a fit that stops at the limit is warned of. A document's
probability is its cell's weight times one scale, at most 1, such that the expected tokens meet the
budget. Whether it is drawn is fixed by a hash of its id and the seed, so reruns agree.

The target of a dimension may be given, as shares of some or all of its categories: those named get
theirs, the others keep their proportions in what is left. A dimension without given shares has its
observed shares raised to a power below 1, so small categories gain; topics within their language, as
words tell languages apart before anything else, and a topic of one language alone can have no more
than that language.

The topic of a document is the nearest of ``TOPICS`` centroids by cosine over hashed words, weighted by
how few documents hold them. Both are fitted on all documents. Texts are cut into words once; word counts
and the vectors made of them are written, the vectors several to a row, and read round by round; a text
without words has topic -1. A round multiplies whole slices of vectors by all centroids at once, in parts
of few enough bits that no sum is rounded: its result depends neither on slices nor on partitions.

Defined results: null source or lang is a category of its own; null or empty text has no tokens and
weight 1, and is kept with the probability of its cell; repeated rows share their fate; centroids at one
distance: the lower number; a category that the target does not name keeps its share of the rest; texts
of any length count whole; an empty table gives no rows; extra columns are carried along.
"""

from __future__ import annotations

import warnings
from collections.abc import Iterator
from dataclasses import dataclass

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame, Window
from pyspark.sql import functions as F

from evigraph.llm import common, text

CELLS, TOPICS = 200_000, 8
#: Hashed words that topics are told by, steps of a unit in the vectors of the fit, and most rounds of it.
WORDS, STEPS, ROUNDS = 1024, 1 << 14, 20
#: Bytes of text whose words are counted at once, entries that a row of packed vectors holds, and vectors that are
#: multiplied at once: what is worked on stays in the processor's memory.
TEXT_BYTES, ENTRIES, VECTORS = 1 << 18, 2048, 256
#: Most sweeps of a fit, and the relative distance from every target at which it is done.
SWEEPS, GAP = 100, 1e-9
DIMENSIONS = ("source", "lang", "topic")


def _word_counts(part: pa.RecordBatch) -> tuple[np.ndarray, np.ndarray, np.ndarray, np.ndarray]:
    """(row, hashed word, count) of a slice, by row, and each row's number of words."""
    pairs, counts, tokens, rows = [], [], [], 0
    for piece in common.slices(part, "text", TEXT_BYTES):
        w = text.words(*common.raw(piece.column("text")), text.SPACED)
        own, n = np.unique((rows + w.rows) * WORDS + (w.hashes & np.uint64(WORDS - 1)).astype(np.int64), return_counts=True)
        pairs.append(own)
        counts.append(n)
        tokens.append(np.diff(w.bounds))
        rows += len(piece)
    key = np.concatenate(pairs)
    return key // WORDS, key % WORDS, np.concatenate(counts), np.concatenate(tokens)


def _vectors(row: np.ndarray, word: np.ndarray, n: np.ndarray, rarity: np.ndarray, rows: int) -> np.ndarray:
    """Weights of the entries such that each row has length 1, or 0."""
    value = np.log1p(n) * rarity[word]
    length = np.sqrt(np.bincount(row, weights=value * value, minlength=rows))
    return value / np.where(length > 0, length, 1)[row]


@dataclass
class Topics:
    rarity: np.ndarray
    centroids: np.ndarray

    def of(self, row: np.ndarray, word: np.ndarray, n: np.ndarray, tokens: np.ndarray) -> np.ndarray:
        """Topic of each row, by its words and their counts."""
        value, held = _vectors(row, word, n, self.rarity, len(tokens)), np.bincount(row, minlength=len(tokens))
        some = np.flatnonzero(held)
        near = np.zeros((len(tokens), len(self.centroids)))
        if len(some):
            begin = (np.cumsum(held) - held)[some]
            near[some] = np.stack([np.add.reduceat(value * c[word], begin) for c in self.centroids], axis=1)
        return np.where(tokens > 0, near.argmax(axis=1), -1).astype(np.int32)


#: Columns of :func:`counted` that hold a row's hashed words and how often it has each.
WORD, COUNT = "_word", "_count"


def counted(docs: DataFrame, keep_text: bool = False) -> DataFrame:
    """``docs``, without text unless it is to be kept, with n_tokens and packed words and counts. Texts are cut
    into words here only."""
    dropped = () if keep_text else ("text",)

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in batches:
            for part in common.slices(batch, "text"):
                row, word, n, tokens = _word_counts(part)
                own = [k for k in part.schema.names if k not in dropped]
                packed = _packed(row, len(part), word.astype(np.int16), n.astype(np.int32))
                yield pa.RecordBatch.from_arrays([*(part.column(k) for k in own), pa.array(tokens), *packed], names=[*own, "n_tokens", WORD, COUNT])

    return docs.mapInArrow(run, common.with_fields(docs, dropped, n_tokens="long", **{WORD: "binary", COUNT: "binary"}))


def _packed(row: np.ndarray, rows: int, *entries: np.ndarray) -> list[pa.Array]:
    cut = np.searchsorted(row, np.arange(rows + 1))
    return [pa.array([x[a:b].tobytes() for a, b in zip(cut, cut[1:], strict=False)], pa.binary()) for x in entries]


def topics(docs: DataFrame, count: int = TOPICS) -> Topics:
    """Word weights and centroids, both from all documents."""
    words = common.written(counted(docs.select("text")))
    model = fitted_to(words, count)
    common.removed(words)
    return model


def fitted_to(words: DataFrame, count: int = TOPICS) -> Topics:
    """The same from rows of :func:`counted`, which are read more than once."""
    def seen(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        total, rows = np.zeros(WORDS, np.int64), 0
        for batch in batches:
            if len(batch):
                total += np.bincount(np.frombuffer(common.raw(batch.column(WORD))[0], np.int16), minlength=WORDS)
                rows += len(batch)
        yield pa.RecordBatch.from_arrays([pa.array(np.append(np.arange(WORDS), -1)), pa.array(np.append(total, rows))], names=["word", "n"])

    held = np.zeros(WORDS)
    rows = 0
    for r in words.select(WORD).mapInArrow(seen, "word long, n long").groupBy("word").agg(F.sum("n").alias("n")).collect():
        if r["word"] < 0:
            rows = r["n"]
        else:
            held[r["word"]] = r["n"]
    rarity = np.log((rows + 1) / (held + 1)) + 1e-3

    def vectors(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in batches:
            for part in common.slices(batch, WORD):
                row, word, n = _entries(part)
                value = np.rint(_vectors(row, word, n, rarity, len(part)) * STEPS).astype(np.int16)
                size = np.bincount(row, minlength=len(part))
                at = np.cumsum(size) - size
                pack = (at + 8 * np.arange(len(part))) // ENTRIES  # so that short vectors, too, are few in a pack
                first = np.append(np.flatnonzero(np.diff(pack, prepend=-1)), len(part))
                pack = np.repeat(np.arange(len(first) - 1), np.diff(first))
                yield pa.RecordBatch.from_arrays([x for rows, kind in ((pack, (size.astype(np.int16),)), (pack[row], (word, value))) for x in _packed(rows, len(first) - 1, *kind)], names=["size", "word", "value"])

    packed = common.written(words.filter("n_tokens > 0").select(WORD, COUNT).mapInArrow(vectors, "size binary, word binary, value binary"))
    fitted = _centroids(packed, count)
    common.removed(packed)
    return Topics(rarity, fitted)


def _entries(batch: pa.RecordBatch) -> tuple[np.ndarray, np.ndarray, np.ndarray]:
    """(row, word, count) of the rows of :func:`counted`."""
    word, at = common.raw(batch.column(WORD))
    count, _ = common.raw(batch.column(COUNT))
    return np.repeat(np.arange(len(batch)), np.diff(at) // 2), np.frombuffer(word, np.int16), np.frombuffer(count, np.int32).astype(np.float64)


def _unpacked(batches: Iterator[pa.RecordBatch]) -> Iterator[tuple[np.ndarray, np.ndarray, np.ndarray]]:
    """(where each vector begins and the last ends, words, values) of the packed vectors, ``VECTORS`` at most at once."""
    for batch in batches:
        size, word, value = (np.frombuffer(common.raw(batch.column(k))[0], np.int16) for k in ("size", "word", "value"))
        at = np.concatenate([[0], np.cumsum(size, dtype=np.int64)])
        for k in range(0, len(size), VECTORS):
            own = at[k : k + VECTORS + 1]
            yield own - own[0], word[own[0] : own[-1]], value[own[0] : own[-1]]


def _exact(centroids: np.ndarray) -> np.ndarray:
    """The centroids in two parts, of 30 and 30 further bits, by one power of two: products with the vectors'
    whole numbers stay below 53 bits, summed in any order."""
    longest = np.linalg.norm(centroids, axis=1).max()
    c = centroids / 2.0 ** np.ceil(np.log2(longest)) if longest else centroids
    high = np.rint(c * 2.0**30) / 2.0**30
    return np.concatenate([high, np.rint((c - high) * 2.0**60) / 2.0**60]).T


def _likeness(at: np.ndarray, word: np.ndarray, value: np.ndarray, exact: np.ndarray) -> np.ndarray:
    """Likeness of each vector to each centroid."""
    dense = np.zeros((len(at) - 1, WORDS))
    dense.ravel()[np.repeat(np.arange(0, dense.size, WORDS), np.diff(at)) + word] = value
    parts = dense @ exact
    half = parts.shape[1] // 2
    return parts[:, :half] + parts[:, half:]


def _furthest(packed: DataFrame, centroids: np.ndarray, sign: int = 1) -> np.ndarray | None:
    """The vector least (or, with a sign of -1, most) like any of the centroids; of several the first by bytes."""
    exact = _exact(centroids)

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        best = None
        for at, word, value in _unpacked(batches):
            score = sign * _likeness(at, word, value, exact).max(axis=1)
            least = score.min()
            if best is None or least <= best[0]:
                found = [(float(least), word[at[i] : at[i + 1]].tobytes(), value[at[i] : at[i + 1]].tobytes()) for i in np.flatnonzero(score == least)]
                best = min(found if best is None else [best, *found])
        if best is not None:
            yield pa.RecordBatch.from_arrays([pa.array([x]) for x in best], names=["score", "word", "value"])

    r = packed.mapInArrow(run, "score double, word binary, value binary").agg(F.min(F.struct("score", "word", "value")).alias("x")).first()["x"]
    if r is None:
        return None
    out = np.zeros(WORDS)
    out[np.frombuffer(r["word"], np.int16)] = np.frombuffer(r["value"], np.int16) / STEPS
    return out


def _sums(packed: DataFrame, centroids: np.ndarray) -> np.ndarray:
    """Sum of the vectors nearest to each centroid. The vectors are whole numbers, so the sums are exact and
    do not depend on the partitions."""
    exact = _exact(centroids)

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        total = np.zeros(len(centroids) * WORDS)
        for at, word, value in _unpacked(batches):
            own = _likeness(at, word, value, exact).argmax(axis=1) if len(centroids) > 1 else np.zeros(len(at) - 1, np.int64)
            total += np.bincount(np.repeat(own * WORDS, np.diff(at)) + word, weights=value, minlength=len(total))
        at = np.flatnonzero(total)
        yield pa.RecordBatch.from_arrays([pa.array(at), pa.array(total[at].astype(np.int64))], names=["at", "n"])

    out = np.zeros(len(centroids) * WORDS)
    for r in packed.mapInArrow(run, "at long, n long").groupBy("at").agg(F.sum("n").alias("n")).collect():
        out[r["at"]] = r["n"]
    return out.reshape(len(centroids), WORDS)


def _centroids(packed: DataFrame, count: int) -> np.ndarray:
    """Unit centroids: each first one far from those before, then rounds of assignment, until none changes."""
    first = _furthest(packed, _sums(packed, np.zeros((1, WORDS))), -1)
    if first is None:
        return np.zeros((1, WORDS))
    chosen = [first]
    while len(chosen) < count:
        chosen.append(_furthest(packed, np.stack(chosen)))
    c, was = np.stack(chosen), None
    for _ in range(ROUNDS):
        now = _sums(packed, c)
        if was is not None and (now == was).all():
            break
        was, size = now, np.linalg.norm(now, axis=1, keepdims=True)
        c = np.where(size > 0, now / np.where(size > 0, size, 1), c)
    return c


def profiled(docs: DataFrame, model: Topics, keep_text: bool = False) -> DataFrame:
    """``docs``, without text unless it is to be kept, with n_tokens and topic."""
    return assigned(counted(docs, keep_text), model)


def assigned(words: DataFrame, model: Topics) -> DataFrame:
    """Rows of :func:`counted` with their topic instead of their words."""
    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in batches:
            if len(batch):
                topic = np.concatenate([model.of(*_entries(part), part.column("n_tokens").to_numpy()) for part in common.slices(batch, WORD)])
                own = [k for k in batch.schema.names if k not in (WORD, COUNT)]
                yield pa.RecordBatch.from_arrays([*(batch.column(k) for k in own), pa.array(topic)], names=[*own, "topic"])

    return words.mapInArrow(run, common.with_fields(words, (WORD, COUNT), topic="int"))


def shares_for(observed: dict, given: dict) -> dict:
    """Given shares for the categories named (none beyond those that occur), the others in their observed
    proportions for the rest; all sum to 1."""
    named = {k: float(v) for k, v in given.items() if k in observed}
    if any(v < 0 for v in named.values()) or sum(given.values()) > 1 + 1e-9:
        raise ValueError("shares are from 0 to 1 and sum to 1 at most")
    others = {k: v for k, v in observed.items() if k not in named}
    left, spread = 1 - sum(named.values()), sum(others.values())
    out = named | ({k: v / spread * left for k, v in others.items()} if spread else {})
    total = sum(out.values())
    return {k: v / total for k, v in out.items()} if total else observed


def tempered(shares: dict, power: float) -> dict:
    """Shares raised to a power below 1: small categories gain, large ones give."""
    raised = {k: v**power for k, v in shares.items() if v > 0}
    total = sum(raised.values())
    return {k: v / total for k, v in raised.items()}


def _unsettled(sweeps: int, worst: float) -> None:
    warnings.warn(f"mixing weights are off their targets by {worst:.3g} after {sweeps} sweeps", RuntimeWarning, stacklevel=3)


def rake(tokens: np.ndarray, keys: list[np.ndarray], targets: list[np.ndarray], sweeps: int = SWEEPS, gap: float = GAP) -> np.ndarray:
    """Factors of cells such that the weighted tokens have the target shares in every dimension."""
    weight, total = np.ones(len(tokens)), tokens.sum()
    for _ in range(sweeps):
        worst = 0.0
        for key, target in zip(keys, targets, strict=True):
            now = np.bincount(key, weights=tokens * weight, minlength=len(target))
            factor = np.where(now > 0, target * total / np.where(now > 0, now, 1), 1.0)
            worst = max(worst, float(np.abs(factor[now > 0] - 1).max(initial=0)))
            weight *= factor[key]
        if worst < gap:
            break
    else:
        _unsettled(sweeps, worst)
    return weight


def _scale(tokens: np.ndarray, weight: np.ndarray, budget: float) -> float:
    """c with sum(tokens * min(1, c * weight)) = budget."""
    order = np.argsort(-weight)
    t, w = tokens[order], weight[order]
    full = np.concatenate([[0], np.cumsum(t)])
    rest = np.concatenate([np.cumsum((t * w)[::-1])[::-1], [0]])
    for k in range(len(t)):  # the k heaviest cells are taken whole
        c = (budget - full[k]) / rest[k] if rest[k] > 0 else 0.0
        if c * w[k] <= 1:
            return max(c, 0.0)
    return float(1 / w[-1]) if len(w) and w[-1] > 0 else 1.0


def _rake_table(cells: DataFrame, targets: dict[str, DataFrame], sweeps: int, gap: float = GAP) -> DataFrame:
    """The same fit for more cells than the driver may hold."""
    total = cells.agg(F.sum("tokens")).first()[0]
    cells = cells.withColumn("weight", F.lit(1.0))
    for k in range(sweeps):
        last, cells = cells, cells.withColumn("off", F.lit(0.0))
        for d, target in targets.items():
            now = cells.groupBy(F.col(d).alias("k")).agg(F.sum(F.col("tokens") * F.col("weight")).alias("now"))
            factor = now.join(target.withColumnRenamed(d, "tk"), F.col("k").eqNullSafe(F.col("tk"))).select("k", "now", F.when(F.col("now") > 0, F.col("share") * total / F.col("now")).otherwise(1.0).alias("factor"))
            cells = cells.join(factor, cells[d].eqNullSafe(factor["k"])).withColumns({"weight": F.col("weight") * F.col("factor"), "off": F.greatest("off", F.when(F.col("now") > 0, F.abs(F.col("factor") - 1)).otherwise(0.0))}).drop("k", "now", "factor")
        cells = common.written(cells)
        if k:
            common.removed(last)
        worst = cells.agg(F.max("off")).first()[0] or 0.0
        cells = cells.drop("off")
        if worst < gap:
            break
    else:
        _unsettled(sweeps, worst)
    return cells


def _within(rows: list, langs: dict, power: float) -> dict:
    """Shares of topics: each language's own, raised to the power, by what the language is to have."""
    held: dict = {}
    for r in rows:
        own = held.setdefault(r["lang"], {})
        own[r["topic"]] = own.get(r["topic"], 0.0) + r["tokens"]
    out: dict = {}
    for lang, own in held.items():
        total = sum(own.values())
        for topic, share in tempered({k: v / total for k, v in own.items()} if total else {}, power).items():
            out[topic] = out.get(topic, 0.0) + langs.get(lang, 0.0) * share
    return out


def calibrated(profile: DataFrame, powers: dict[str, float] | None = None, targets: dict[str, dict] | None = None, keep: float = 0.5, cells_limit: int = CELLS, sweeps: int = SWEEPS) -> DataFrame:
    """(source, lang, topic, weight, probability) per cell of ``profile`` (the three and n_tokens). The
    target of a dimension is given, or its shares raised to its power; the sample is to hold the share
    ``keep`` of all tokens."""
    powers, targets = {"source": 0.7, "lang": 0.7, "topic": 0.5} | (powers or {}), targets or {}
    cells = common.written(profile.groupBy(*DIMENSIONS).agg(F.sum("n_tokens").cast("double").alias("tokens")))
    kinds = ", ".join(f"{d} {dict(cells.dtypes)[d]}" for d in DIMENSIONS) + ", weight double, probability double"
    spark = profile.sparkSession
    if common.small(cells, cells_limit):
        rows = cells.orderBy(*DIMENSIONS).collect()
        tokens = np.array([r["tokens"] for r in rows], float)
        keys, aims, named = [], [], {}
        for d in DIMENSIONS:
            names = {k: i for i, k in enumerate(dict.fromkeys(r[d] for r in rows))}
            key = np.array([names[r[d]] for r in rows], np.int64)
            share = dict(zip(names, (np.bincount(key, weights=tokens, minlength=len(names)) / max(tokens.sum(), 1)).tolist(), strict=True))
            if d in targets:
                aim = shares_for(share, targets[d])
            elif d == "topic":
                aim = _within(rows, dict(zip(named["lang"], aims[1], strict=True)), powers[d])
            else:
                aim = tempered(share, powers[d])
            named[d] = names
            keys.append(key)
            aims.append(np.array([aim.get(k, 0.0) for k in names]))
        weight = rake(tokens, keys, aims, sweeps) if tokens.sum() else np.ones(len(rows))
        c = _scale(tokens, weight, keep * tokens.sum()) if tokens.sum() else 1.0
        return spark.createDataFrame([(*(r[d] for d in DIMENSIONS), float(w), float(min(1, c * w))) for r, w in zip(rows, weight, strict=True)], kinds)
    total = cells.agg(F.sum("tokens")).first()[0] or 1.0
    aims = {}
    for d in DIMENSIONS:
        kind = dict(cells.dtypes)[d]
        observed = common.written(cells.groupBy(d).agg((F.sum("tokens") / total).alias("share")))
        if d in targets:
            given = spark.createDataFrame([(k, float(v)) for k, v in targets[d].items()], f"k {kind}, given double")
            j = observed.join(given, F.col(d).eqNullSafe(F.col("k")), "left")
            t = j.agg(F.coalesce(F.sum("given"), F.lit(0.0)).alias("named"), F.coalesce(F.sum(F.when(F.col("given").isNull(), F.col("share"))), F.lit(0.0)).alias("spread")).first()
            if sum(targets[d].values()) > 1 + 1e-9 or min(targets[d].values(), default=0) < 0:
                raise ValueError("shares are from 0 to 1 and sum to 1 at most")
            left = (1 - t["named"]) / t["spread"] if t["spread"] else 0.0
            aim = j.select(d, F.coalesce("given", F.col("share") * left).alias("share"))
            whole = t["named"] + left * t["spread"]
        elif d == "topic":
            both = cells.groupBy("lang", "topic").agg(F.sum("tokens").alias("t")).filter("t > 0")
            raised = common.written(both.withColumn("t", F.pow(F.col("t") / F.sum("t").over(Window.partitionBy("lang")), F.lit(powers[d]))))
            raised = raised.withColumn("t", F.col("t") / F.sum("t").over(Window.partitionBy("lang")))
            of = aims["lang"].select(F.col("lang").alias("l2"), F.col("share").alias("of"))
            aim = raised.join(of, F.col("lang").eqNullSafe(F.col("l2"))).groupBy("topic").agg(F.sum(F.col("t") * F.col("of")).alias("share"))
            whole = aim.agg(F.sum("share")).first()[0]
        else:
            aim = observed.filter("share > 0").withColumn("share", F.pow("share", F.lit(powers[d])))
            whole = aim.agg(F.sum("share")).first()[0]
        aims[d] = common.written(aim.withColumn("share", F.col("share") / whole) if whole else observed)
    fitted = _rake_table(cells, aims, sweeps)
    low, high = 0.0, 1.0
    spent = lambda c: fitted.agg(F.sum(F.col("tokens") * F.least(F.lit(1.0), F.lit(c) * F.col("weight")))).first()[0] or 0.0
    while spent(high) < keep * total and high < 1e9:
        high *= 4
    for _ in range(40):
        mid = (low + high) / 2
        low, high = (mid, high) if spent(mid) < keep * total else (low, mid)
    return fitted.withColumn("probability", F.least(F.lit(1.0), F.lit(high) * F.col("weight"))).drop("tokens")


def mixed(docs: DataFrame, keep: float = 0.5, seed: int = 7, keep_text: bool = False, **options) -> DataFrame:
    """``docs``, without text unless it is to be kept, with n_tokens, topic, weight, probability and drawn."""
    words = common.written(counted(docs, keep_text))
    model = fitted_to(words)
    rows = assigned(words, model)
    if keep_text:  # texts are not written again for the cells
        profile = assigned(words.select("source", "lang", "n_tokens", WORD, COUNT), model)
    else:
        rows = profile = common.written(rows)
    cells = calibrated(profile.select(*DIMENSIONS, "n_tokens"), keep=keep, **options)
    right = F.broadcast(cells) if common.small(cells, CELLS) else cells
    on = F.lit(True)
    for d in DIMENSIONS:
        on = on & rows[d].eqNullSafe(right[d])
    out = rows.join(right, on, "left").drop(*(right[d] for d in DIMENSIONS))
    u = F.shiftrightunsigned(F.xxhash64(F.lit(seed), F.col("doc_id").cast("string")), 11) / F.lit(float(1 << 53))
    return out.withColumn("drawn", u < F.col("probability"))


def sampled(docs: DataFrame, **options) -> DataFrame:
    rows = mixed(common.apart(docs, "doc_id", "source", "lang"), keep_text=True, **options)
    return common.unwrapped(rows.filter("drawn"), docs, text=F.col("text"))
