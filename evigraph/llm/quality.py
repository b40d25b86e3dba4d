"""Hierarchical empirical Bayes quality classifier.

Document evidence is the log ratio of a document as bad ("junk" or "toxic") against good, from a softmax
regression over words, word stems and binned shape measures, hashed to ``BUCKETS`` features. Features are
chosen from all labelled documents, by sums on the executors: all those whose counts differ between
the kinds beyond chance. The regression is fitted on all labelled documents: their lists of chosen features
are written once, and each step sums loss and gradient over them on the executors. The soft verdicts of all
documents are then summed per host and per path; host rates are shrunk toward the global rate, path
rates toward their host's, with prior strengths found from the spread of the rates (method of moments).
A document is judged by its evidence at the odds of its path.

Defined results: null text counts as empty; null host or path is a site of its own; without labels, or
with labels of one class, evidence is 0 and every document is kept; a document that is bad with a
probability of exactly 0.5 goes; repeated label rows of a document unite (worst wins), repeated documents
are judged alike; texts of any length are read whole; an empty table gives no rows; extra columns are
carried along.
"""

from __future__ import annotations

from collections.abc import Iterator

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from evigraph.llm import common, text

#: Features that words, stems and shapes are hashed to, the least count of one that is chosen, and how many
#: deviations from chance it must show.
BUCKETS, LEAST, DEVIATIONS = 1 << 18, 8, 4.0
#: Parts of a document's loss and gradient are whole numbers of one in ``UNIT``; the fit ends below this gain of a step.
UNIT, LEAST_GAIN = float(1 << 24), 1e-3
#: Sites that are broadcast at most; more are joined by shuffle.
SITES = 100_000
STEM = 5


def _distinct(rows: np.ndarray, hashes: np.ndarray) -> tuple[np.ndarray, np.ndarray]:
    """Distinct (row, hash) pairs by one sort; 42 bits of the hash are kept."""
    pairs = np.unique(rows.astype(np.uint64) << np.uint64(42) | hashes >> np.uint64(22))
    return (pairs >> np.uint64(42)).astype(np.int64), pairs & np.uint64((1 << 42) - 1)


def _features(part: pa.RecordBatch) -> tuple[np.ndarray, np.ndarray]:
    """(row, feature) pairs, each once."""
    body, at = common.raw(part.column("text"))
    w = text.words(body, at, text.ALNUM)
    rows, n = w.rows, len(part)
    long = np.flatnonzero(w.end - w.begin > STEM)
    stems = text.Rolling(w.data).of(w.begin[long], w.begin[long] + STEM) ^ np.uint64(0x5B << 50)
    r1, f1 = _distinct(rows, w.hashes)
    r2, f2 = _distinct(rows[long], stems)

    def per_row(mask: np.ndarray) -> np.ndarray:
        return np.diff(np.concatenate([[0], np.cumsum(mask)])[at])

    size = np.maximum(1, np.diff(at))
    inside = text.SPACED[body]
    before = np.concatenate([[False], inside[:-1]])[: len(inside)]
    before[at[:-1][at[:-1] < len(body)]] = False
    tokens, distinct = per_row(inside & ~before), np.bincount(r1, minlength=n)
    words_n = np.maximum(1, np.diff(w.bounds))
    upper = per_row((body >= 65) & (body <= 90)) / np.maximum(1, per_row(text.ALNUM[body]))
    symbol = per_row(np.isin(body, np.frombuffer(b"!#$%&*+<=>@\\^_|~{}[]", np.uint8))) / size
    digit = per_row((body >= 48) & (body <= 57)) / size
    breaks = per_row(body == 10) / np.maximum(1, tokens)
    mean = per_row(text.ALNUM[body]) / words_n
    shapes = [
        np.digitize(upper, [0.02, 0.06, 0.12, 0.25, 0.5, 0.8]), np.digitize(symbol, [0.002, 0.01, 0.03, 0.06, 0.1, 0.2]), np.digitize(digit, [0.01, 0.05, 0.1, 0.3]),
        np.digitize(distinct / words_n, [0.02, 0.05, 0.1, 0.2, 0.3, 0.4, 0.5, 0.7, 0.9]) * 6 + np.digitize(words_n, [20, 60, 150, 500, 2000]), np.digitize(breaks, [0.002, 0.01, 0.05, 0.2, 0.5]),
        np.digitize(mean, [2, 3, 4, 5, 6, 7, 8, 10, 15]), np.digitize(tokens, [1, 5, 20, 60, 150, 500, 2000]),
    ]
    r3 = np.tile(np.arange(n), len(shapes))
    f3 = text.mix(np.concatenate([s.astype(np.uint64) + np.uint64(1000 * (k + 1)) for k, s in enumerate(shapes)])) >> np.uint64(22)
    size = BUCKETS.bit_length() - 1
    key = np.unique(np.concatenate([r1, r2, r3]) << size | (np.concatenate([f1, f2, f3]) >> np.uint64(42 - size)).astype(np.int64))
    return key >> size, key & (BUCKETS - 1)


def weights(docs: DataFrame, labels: DataFrame) -> dict:
    """Log ratios of the kept features for both kinds of bad documents, from all labelled rows."""
    marked = labels.filter("doc_id is not null").groupBy("doc_id").agg(F.min("quality").alias("q"), F.max("toxic").alias("t"))
    kind = F.when(F.col("t") == 1, 2).when(F.col("q") == 0, 1).when(F.col("q") == 1, 0)
    marked = marked.select("doc_id", kind.cast("int").alias("kind")).filter("kind is not null")
    known = common.joined_checked(docs.select("doc_id", "text"), marked, ["doc_id"], "inner", 1_000_000)

    def count(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        total = np.zeros((BUCKETS + 1, 3), np.int64)  # the last row counts documents
        for batch in batches:
            for part in _slices(batch):
                rows, feature = _features(part)
                kind = part.column("kind").to_numpy(zero_copy_only=False)
                total += np.bincount(feature * 3 + kind[rows], minlength=total.size).reshape(total.shape)
                total[-1] += np.bincount(kind, minlength=3)
        at = np.flatnonzero(total.any(axis=1))
        yield pa.RecordBatch.from_arrays([pa.array(at), *(pa.array(total[at, k]) for k in range(3))], names=["f", "n0", "n1", "n2"])

    sums = common.written(known.select("text", "kind").mapInArrow(count, "f long, n0 long, n1 long, n2 long").groupBy("f").agg(*(F.sum(f"n{k}").alias(f"n{k}") for k in range(3))))
    total = sums.filter(F.col("f") == BUCKETS).first()
    empty = {"f": np.zeros(0, np.int64), "w": np.zeros((0, 2)), "base": np.zeros(2), "rate": 0.1}
    if total is None or not total["n0"] or not total["n1"] + total["n2"]:
        return empty
    t = [total[f"n{k}"] for k in range(3)]

    def deviation(k: int):
        n, p = F.col(f"n{k}") + F.col("n0"), t[k] / (t[k] + t[0])
        return F.abs(F.col(f"n{k}") - n * p) / F.sqrt(n * max(p * (1 - p), 1e-9) + 1)

    top = sums.filter((F.col("f") < BUCKETS) & (F.col("n0") + F.col("n1") + F.col("n2") >= LEAST) & (F.greatest(deviation(1), deviation(2)) >= DEVIATIONS)).select("f").toPandas()
    if not len(top):
        return empty
    f = np.sort(top["f"].to_numpy(np.int64))

    def gather(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in batches:
            for part in _slices(batch):
                row, at = _chosen(part, f)
                kind, count = part.column("kind").to_numpy(zero_copy_only=False), np.bincount(row, minlength=len(part))
                packed = [kind.astype(np.int8), count.astype(np.int32), at.astype(place)]
                yield pa.RecordBatch.from_arrays([pa.array([x.tobytes()], pa.binary()) for x in packed], names=["kind", "count", "at"])

    place = np.uint16 if len(f) <= 1 << 16 else np.int32
    lists = common.written(known.select("text", "kind").mapInArrow(gather, "kind binary, count binary, at binary"))
    return {"f": f} | _softmax(lists, t, len(f))


def _slices(batch: pa.RecordBatch) -> Iterator[pa.RecordBatch]:
    """Slices of fewer rows than a key has room for."""
    for part in common.slices(batch, "text"):
        for k in range(0, len(part), 1 << 20):
            yield part.slice(k, 1 << 20)


def _chosen(part: pa.RecordBatch, f: np.ndarray) -> tuple[np.ndarray, np.ndarray]:
    """(row, place in ``f``) of the chosen features of each row, by row."""
    rows, feature = _features(part)
    place = np.full(BUCKETS, -1, np.int64)
    place[f] = np.arange(len(f))
    at = place[feature]
    return rows[at >= 0], at[at >= 0]


def _gradient(lists: DataFrame, w: np.ndarray, base: np.ndarray) -> tuple[float, np.ndarray, np.ndarray]:
    """Mean loss over all of ``lists`` (the kinds of many documents, their counts of features, these one after
    another) and its gradients for weights and base. Each document's part is rounded to a whole number of ``UNIT``, so that the sums do not depend on how rows are dealt."""
    size, own = len(w), [np.ascontiguousarray(w[:, k]) for k in (0, 1)]
    place = np.uint16 if size <= 1 << 16 else np.int32

    def add(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        total = np.zeros((size + 2, 2), np.int64)  # then base, then loss and documents
        for batch in batches:
            for kind, count, at in zip(*(batch.column(c) for c in ("kind", "count", "at")), strict=True):
                kind, count = np.frombuffer(kind.as_buffer(), np.int8), np.frombuffer(count.as_buffer(), np.int32)
                at = np.frombuffer(at.as_buffer(), place).astype(np.int64)
                row = np.repeat(np.arange(len(kind)), count)
                z = np.stack([np.bincount(row, weights=own[k][at], minlength=len(kind)) + base[k] for k in (0, 1)])
                aim = kind == np.array([[1], [2]])
                top = np.maximum(z.max(axis=0), 0)
                e = np.exp(z - top)
                whole = e.sum(axis=0) + np.exp(-top)
                gap = np.rint((e / whole - aim) * UNIT)
                for k in (0, 1):
                    total[:size, k] += np.bincount(at, weights=gap[k][row], minlength=size).astype(np.int64)
                total[size] += gap.sum(axis=1).astype(np.int64)
                total[size + 1] += [int(np.rint((np.log(whole) + top - (z * aim).sum(axis=0)) * UNIT).sum()), len(kind)]
        at = np.flatnonzero(total.any(axis=1))
        yield pa.RecordBatch.from_arrays([pa.array(at), *(pa.array(total[at, k]) for k in (0, 1))], names=["f", "g1", "g2"])

    rows = lists.mapInArrow(add, "f long, g1 long, g2 long").groupBy("f").agg(F.sum("g1").alias("g1"), F.sum("g2").alias("g2")).toPandas()
    total = np.zeros((size + 2, 2), np.int64)
    total[rows["f"].to_numpy()] = rows[["g1", "g2"]].to_numpy()
    n = total[-1, 1]
    return total[-1, 0] / UNIT / n, total[:size] / UNIT / n, total[size] / UNIT / n


def _softmax(lists: DataFrame, counts: list[int], size: int, penalty: float = 3e-4, steps: int = 100, memory: int = 10) -> dict:
    """Weights of kinds 1 and 2 against kind 0, by quasi-Newton steps of which each reads all of ``lists`` in a job
    of its own; ends when a step lowers the loss by less than ``LEAST_GAIN`` of it."""
    share = np.array(counts) / sum(counts)
    start = np.log(np.maximum(share[1:], 1e-9) / max(share[0], 1e-9))

    def loss(x: np.ndarray) -> tuple[float, np.ndarray]:
        w = x[:-2].reshape(size, 2)
        value, gw, gb = _gradient(lists, w, x[-2:])
        return value + penalty / 2 * float((w * w).sum()), np.concatenate([(gw + penalty * w).ravel(), gb])

    x = np.concatenate([np.zeros(2 * size), start])
    value, g = loss(x)
    past: list[tuple[np.ndarray, np.ndarray]] = []
    for _ in range(steps):
        d, kept = -g, []
        for s, y in reversed(past):
            kept.append((s @ d) / (s @ y))
            d = d - kept[-1] * y
        d = d * ((past[-1][0] @ past[-1][1]) / (past[-1][1] @ past[-1][1]) if past else 1 / max(np.abs(g).max(), 1e-12))
        for (s, y), c in zip(past, reversed(kept), strict=True):
            d = d + (c - (y @ d) / (s @ y)) * s
        length, slope = 1.0, float(g @ d)
        while True:
            found, new = loss(x + length * d)
            if found <= value + 1e-4 * length * slope or length < 1e-4:
                break
            length /= 2
        if found >= value:
            break
        s, y, gain = length * d, new - g, value - found
        x, value, g = x + s, found, new
        if s @ y > 0:
            past = [*past, (s, y)][-memory:]
        if gain <= LEAST_GAIN * value:
            break
    return {"w": x[:-2].reshape(size, 2).copy(), "base": x[-2:].copy(), "rate": min(max(1 - share[0], 1e-3), 1 - 1e-3)}


def evidence(docs: DataFrame, model: dict, keep_text: bool = False) -> DataFrame:
    """``docs``, without text unless it is to be kept, with ``evidence``: the log ratio of the text as bad
    against as good."""
    dropped = () if keep_text else ("text",)
    odds = float(np.log(model["rate"] / (1 - model["rate"])))

    def score(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in batches:
            for part in _slices(batch):
                both = np.zeros(len(part))
                if len(model["f"]):
                    rows, at = _chosen(part, model["f"])
                    z = [np.bincount(rows, weights=model["w"][at, k], minlength=len(part)) + model["base"][k] for k in (0, 1)]
                    both = np.clip(np.logaddexp(*z) - odds, -30, 30)
                kept = [k for k in part.schema.names if k not in dropped]
                yield pa.RecordBatch.from_arrays([*(part.column(k) for k in kept), pa.array(both)], names=[*kept, "evidence"])

    return docs.mapInArrow(score, common.with_fields(docs, dropped, evidence="double"))


def site_rates(scored: DataFrame, host: str, path: str, rate: float) -> DataFrame:
    """(host, path, prior): the rate of bad documents of each path, shrunk to its host's and that to
    the global one."""
    soft = F.lit(1.0) / (1.0 + F.exp(-(F.col("evidence") + float(np.log(rate / (1 - rate))))))
    paths = common.written(scored.groupBy(F.col(host).alias("host"), F.col(path).alias("path")).agg(F.sum(soft).alias("bad"), F.count("*").alias("n")))
    hosts = paths.groupBy("host").agg(F.sum("bad").alias("hb"), F.sum("n").alias("hn"))

    def strength(df: DataFrame, bad: str, n: str) -> tuple[float, float]:
        """Global rate, and the prior count with which rates spread as observed."""
        r = F.col(bad) / F.col(n)
        t = df.agg(F.sum(bad).alias("b"), F.sum(n).alias("n"), F.count("*").alias("k"), F.sum(F.col(n) * r * r).alias("s2"), F.sum(F.col(n) * F.col(n)).alias("nn")).first()
        if not t["n"]:
            return rate, 10.0
        m = min(max(t["b"] / t["n"], 1e-4), 1 - 1e-4)
        within = m * (1 - m)
        room = t["n"] - t["nn"] / t["n"]
        between = max((t["s2"] - t["n"] * m * m - (t["k"] - 1) * within) / room, 0.0) if room > 0 else 0.0
        return m, min(max(within / between - 1, 2.0), 1e4) if between > 0 else 1e4

    mean, s1 = strength(hosts, "hb", "hn")
    _, s2 = strength(paths, "bad", "n")
    hosts = hosts.withColumn("hr", (F.col("hb") + s1 * mean) / (F.col("hn") + s1))
    out = paths.join(hosts.withColumnRenamed("host", "h2"), F.col("host").eqNullSafe(F.col("h2"))).select("host", "path", ((F.col("bad") + s2 * F.col("hr")) / (F.col("n") + s2)).alias("prior"))
    return common.written(out)


def judged(docs: DataFrame, labels: DataFrame, host: str = "source", path: str = "lang", known: DataFrame | None = None, keep_text: bool = False) -> DataFrame:
    """``docs``, without text unless it is to be kept, with evidence, prior (its path's rate), p_bad and keep;
    ``known`` may name another table of documents that the labels belong to. Evidence is found once and
    written."""
    model = weights(known if known is not None else docs, labels)
    scored = common.written(evidence(docs, model, keep_text))
    rates = site_rates(scored.select(host, path, "evidence"), host, path, model["rate"])
    right = F.broadcast(rates) if common.small(rates, SITES) else rates
    out = scored.join(right, scored[host].eqNullSafe(right["host"]) & scored[path].eqNullSafe(right["path"]), "left").drop(right["host"], right["path"])
    out = out.withColumn("prior", F.coalesce("prior", F.lit(model["rate"])))
    logit = F.col("evidence") + F.log(F.col("prior") / (1 - F.col("prior")))
    out = out.withColumn("p_bad", 1.0 / (1.0 + F.exp(-logit)))
    return out.withColumn("keep", F.col("p_bad") < 0.5) if len(model["f"]) else out.withColumn("keep", F.lit(True))


def good(docs: DataFrame, labels: DataFrame) -> DataFrame:
    rows = judged(common.apart(docs, "source", "lang"), labels, known=docs.select("doc_id", "text"), keep_text=True)
    return common.unwrapped(rows.filter("keep"), docs, text=F.col("text"))
