"""Near-duplicate line removal by segment partition.

Lines equal after trimming collapse to one. A line is cut into threshold + 1 segments of near equal
length; if two lines are within the threshold in edit distance, some segment of the earlier-indexed
one stands unchanged in the other, shifted by at most the edits on either side of it. Segments go to an
index keyed by (line length, segment number, content hash); every line probes the index of each length
it may match with the substrings at the places that the shift allows. Pairs that meet are screened by
the parity of their bigram counts, which one edit changes in at most four bits, and then verified with
a bit-parallel edit distance that stops once the threshold is passed.

Lines within ``edits`` of each other, directly or through others, are a group. Of a group the line that
occurs first (smallest doc_id, then line number) stays; repeats of any line go. To find the groups, each
list of the index is first met by one line of it, which ties most of what belongs together; pairs that
are tied already are not made again, so a large group of variants costs no square of its size.

Defined results: null text has no lines and stays null, empty text is one empty line; lines shorter
than ``least`` characters are never judged; rows that repeat a doc_id are told apart by
their text and rows equal in both are judged as one; a null doc_id comes last in the order; further columns are carried along.
"""

from __future__ import annotations

from collections.abc import Iterator

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame, Window
from pyspark.sql import functions as F

from evigraph.llm import common, text

_U = np.uint64
_TRIM = " \t\r\x0b\x0c"


def _line_runs(body: np.ndarray, at: np.ndarray) -> tuple[np.ndarray, np.ndarray, np.ndarray, np.ndarray]:
    """Begin, end (trimmed), row and number of every line of the rows of code points."""
    breaks = np.flatnonzero(body == 10)
    begin = np.concatenate([at[:-1], breaks + 1])
    # a break belongs to the row it stands in, even where it ends the row's text
    row = np.concatenate([np.arange(len(at) - 1), np.searchsorted(at, breaks, side="right") - 1])
    place = np.lexsort((begin, row))
    begin, row = begin[place], row[place]
    last = np.append(row[1:] != row[:-1], True)[: len(row)]
    end = np.where(last, at[row + 1], np.append(begin[1:] - 1, 0)[: len(row)])
    blank = np.zeros(128, bool)
    blank[[ord(c) for c in _TRIM]] = True
    for step in (0, 1):  # white space before, then after
        left = np.flatnonzero(begin < end)
        while len(left):
            c = body[begin[left] if step == 0 else end[left] - 1]
            left = left[(c < 128) & blank[np.minimum(c, 127)]]
            if step == 0:
                begin[left] += 1
            else:
                end[left] -= 1
            left = left[begin[left] < end[left]]
    first = np.searchsorted(row, np.arange(len(at) - 1))
    return begin, end, row, np.arange(len(row)) - first[row]


def occurrences(docs: DataFrame, least: int) -> DataFrame:
    """row_key, doc_id, no and line (two hashes) of every judged line."""
    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in batches:
            for part in common.slices(batch, "text"):
                body, at = text.points(*common.raw(part.column("text")))
                begin, end, row, no = _line_runs(body, at)
                ok = end - begin >= least
                begin, end, row, no = begin[ok], end[ok], row[ok], no[ok]
                rolling = text.Rolling(body)
                yield pa.RecordBatch.from_arrays([
                    part.column("row_key").take(pa.array(row)), part.column("doc_id").take(pa.array(row)), pa.array(no.astype(np.int32)), pa.array(rolling.of(begin, end).view(np.int64)),
                ], names=["row_key", "doc_id", "no", "line"])

    kind = dict(docs.dtypes)["doc_id"]
    return docs.select("row_key", "doc_id", "text").mapInArrow(run, f"row_key long, doc_id {kind}, no int, line long")


def _segments(length: np.ndarray, k: int, parts: int) -> tuple[np.ndarray, np.ndarray]:
    """Begin and end of the k-th of near equal segments; later ones take the rest."""
    short = length // parts
    extra = length - short * parts
    begin = k * short + np.maximum(0, k - (parts - extra))
    return begin, begin + short + (k >= parts - extra)


def parity(body: np.ndarray, begin: np.ndarray, end: np.ndarray) -> np.ndarray:
    """64 bits: for each bucket, whether a run has an odd number of the character pairs in it."""
    if len(body) < 2 or not len(begin):
        return np.zeros(len(begin), _U)
    pair = text.mix((body[:-1].astype(_U) << _U(21) | body[1:].astype(_U)) + _U(1)) & _U(63)
    bits = np.zeros(len(body), _U)
    np.bitwise_xor.accumulate(_U(1) << pair, out=bits[1:])
    return np.where(end - begin >= 2, bits[np.maximum(end - 1, 0)] ^ bits[begin], _U(0))


def index_rows(docs: DataFrame, edits: int, least: int) -> DataFrame:
    """line, side (0: index, 1: probe), key, parity for each distinct line of a slice."""
    parts = edits + 1

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in batches:
            for part in common.slices(batch, "text"):
                body, at = text.points(*common.raw(part.column("text")))
                begin, end, *_ = _line_runs(body, at)
                ok = end - begin >= least
                begin, end = begin[ok], end[ok]
                rolling = text.Rolling(body)
                line, first = np.unique(rolling.of(begin, end), return_index=True)
                begin, end = begin[first], end[first]
                size, sign = end - begin, parity(body, begin, end)
                out: list[tuple[np.ndarray, np.ndarray, np.ndarray]] = []

                def add(which, length, k, b, e, side):
                    key = text.mix(rolling.of(begin[which] + b, begin[which] + e) + length.astype(_U) * _U(0x9E3779B97F4A7C15) + _U(k + 1))
                    out.append((which, key, np.full(len(which), side, bool)))

                every = np.arange(len(line))
                for k in range(parts):
                    add(every, size, k, *_segments(size, k, parts), False)
                    for less in range(edits + 1):  # the indexed line is shorter by this, or as long
                        length = size - less
                        b, e = _segments(length, k, parts)
                        # edits left of the segment number at most k, right of it at most edits - k
                        for move in range(max(-k, less - (edits - k)), min(k, less + (edits - k)) + 1):
                            fits = np.flatnonzero((length > 0) & (b + move >= 0) & (e + move <= size))
                            add(fits, length[fits], k, b[fits] + move, e[fits] + move, True)
                if not out:
                    continue
                which, key, side = (np.concatenate(x) for x in zip(*out, strict=True))
                yield pa.RecordBatch.from_arrays([pa.array(line[which].view(np.int64)), pa.array(side), pa.array(key.view(np.int64)), pa.array(sign[which].view(np.int64))], names=["line", "probe", "key", "parity"])

    return docs.select("text").mapInArrow(run, "line long, probe boolean, key long, parity long")


def within(a: bytes, b: bytes, edits: int) -> bool:
    """Whether the edit distance of two code point strings is at most ``edits``: common ends go, then
    the bit-parallel columns of the distance matrix are kept for the band around its diagonal."""
    x, y = a.decode("utf-8", "replace"), b.decode("utf-8", "replace")
    if abs(len(x) - len(y)) > edits:
        return False
    k = 0
    most = min(len(x), len(y))
    while k < most and x[k] == y[k]:
        k += 1
    x, y = x[k:], y[k:]
    k, most = 0, min(len(x), len(y))
    while k < most and x[-1 - k] == y[-1 - k]:
        k += 1
    x, y = x[: len(x) - k], y[: len(y) - k]
    if len(x) > len(y):
        x, y = y, x
    if not x or edits == 0:
        return len(y) <= edits
    m, width = len(x), 2 * edits + 1
    masks: dict[str, int] = {}
    for i, c in enumerate(x):
        masks[c] = masks.get(c, 0) | 1 << i
    full = (1 << m) - 1
    up, down, score = full, 0, m
    for j, c in enumerate(y):
        eq = masks.get(c, 0)
        # only rows within the band can still lie on a path of few enough edits
        low = max(0, j - edits)
        eq &= ((1 << (width + 1)) - 1) << low if low < m else 0
        cross = ((((eq & up) + up) ^ up) | eq | down) & full
        hp, hn = down | (full & ~(cross | up)), up & cross
        if hp >> (m - 1) & 1:
            score += 1
        elif hn >> (m - 1) & 1:
            score -= 1
        hp, hn = (hp << 1 | 1) & full, hn << 1 & full
        up, down = hn | (full & ~(cross | hp)), hp & cross
        if score - (len(y) - 1 - j) > edits:
            return False
    return score <= edits


def line_texts(docs: DataFrame, wanted: DataFrame, least: int) -> DataFrame:
    """line, body of the lines in ``wanted`` (line, row_key, no)."""
    per = wanted.groupBy("row_key").agg(F.collect_list(F.struct("no", "line")).alias("asked"))
    lines = docs.select("row_key", "text").join(per, "row_key").select(F.explode("asked").alias("a"), F.split("text", "\n").alias("l"))
    return lines.select(F.col("a.line").alias("line"), F.trim(F.get("l", F.col("a.no")), F.lit(_TRIM)).alias("body"))


def _verified(pairs: DataFrame, bodies: DataFrame, edits: int) -> DataFrame:
    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in batches:
            x, y = batch.column("x").to_pylist(), batch.column("y").to_pylist()
            ok = pa.array([within(a.encode(), b.encode(), edits) for a, b in zip(x, y, strict=True)], pa.bool_())
            yield pa.RecordBatch.from_arrays([batch.column("line").filter(ok), batch.column("other").filter(ok)], names=["a", "b"])

    both = pairs.join(bodies.withColumnRenamed("body", "x"), "line").join(bodies.select(F.col("line").alias("other"), F.col("body").alias("y")), "other")
    return both.select("line", "other", "x", "y").mapInArrow(run, "a long, b long")


def judged(docs: DataFrame, edits: int = 2, least: int = 20) -> tuple[DataFrame, DataFrame]:
    """(rows, drops): ``docs`` wrapped and with a row_key, and per row_key the line numbers dropped as
    repeats (exact) and as near repeats (near)."""
    if edits < 0 or least < 4 * (edits + 1):
        raise ValueError("lines must be long enough for segments of at least four characters")
    # equal rows get equal keys; the rows behind one key are told apart by their number
    rows = common.wrapped(docs, "doc_id", "text").withColumn("row_key", F.xxhash64(F.coalesce(F.col("doc_id").cast("string"), F.lit("")), F.coalesce("text", F.lit(""))))
    seen = common.written(occurrences(rows, least).distinct())
    order = F.struct(F.col("doc_id").isNull().alias("last"), "doc_id", "row_key", "no")
    firsts = common.written(seen.groupBy("line").agg(F.min(order).alias("first")))
    exact = seen.join(firsts, "line").filter(F.struct(F.col("doc_id").isNull().alias("last"), "doc_id", "row_key", "no") != F.col("first")).select("row_key", "no")

    # keys that lines alone hold lead nowhere; what is left is small
    whole = Window.partitionBy("key")
    keyed = index_rows(rows, edits, least).withColumns({"lo": F.min("line").over(whole), "hi": F.max("line").over(whole), "any": F.bool_or("probe").over(whole), "all": F.bool_and("probe").over(whole)})
    keyed = common.written(keyed.filter("lo <> hi and any and not all").drop("lo", "hi", "any", "all").distinct())
    close = F.bit_count(F.col("pa").bitwiseXOR(F.col("pb"))) <= 4 * edits
    probe = keyed.filter("probe").select("key", F.col("line").alias("a"), F.col("parity").alias("pa"))
    index = keyed.filter("not probe").select("key", F.col("line").alias("b"), F.col("parity").alias("pb"))

    def verified(met: DataFrame) -> DataFrame:
        pairs = common.written(met.select(F.least("a", "b").alias("line"), F.greatest("a", "b").alias("other")).distinct())
        ends = pairs.select("line").unionByName(pairs.select(F.col("other").alias("line"))).distinct()
        wanted = firsts.join(ends, "line", "left_semi").select("line", F.col("first.row_key").alias("row_key"), F.col("first.no").alias("no"))
        return common.written(_verified(pairs, line_texts(rows.dropDuplicates(["row_key"]), wanted, least), edits))

    # first one line of each list against the others: what it matches is tied and need not meet again
    leaders = index.groupBy("key").agg(F.min(F.struct("b", "pb")).alias("l")).select("key", "l.*")
    found = verified(probe.join(leaders, "key").filter("a <> b").filter(close))
    tied = common.components(found)
    tie_a, tie_b = (tied.select(F.col("id").alias(x), F.col("component_id").alias(f"t{x}")) for x in "ab")
    probe = probe.join(tie_a, "a", "left").withColumn("ta", F.coalesce("ta", "a"))
    index = index.join(tie_b, "b", "left").withColumn("tb", F.coalesce("tb", "b"))
    more = verified(probe.join(index, "key").filter("ta <> tb").filter(close))
    groups = common.components(found.unionByName(more)).withColumnRenamed("id", "line")
    lead = firsts.join(groups, "line")
    best = lead.groupBy("component_id").agg(F.min("first").alias("best"))
    near = lead.join(best, "component_id").filter("first <> best").select("line")
    near = firsts.join(near, "line", "left_semi").select(F.col("first.row_key").alias("row_key"), F.col("first.no").alias("no"))
    drops = exact.select("row_key", "no", F.lit(True).alias("exact")).unionByName(near.select("row_key", "no", F.lit(False).alias("exact")))
    drops = drops.groupBy("row_key").agg(F.collect_list(F.when(F.col("exact"), F.col("no"))).alias("exact"), F.collect_list(F.when(~F.col("exact"), F.col("no"))).alias("near"))
    return rows, drops


def _kept(lines, drop):
    return F.array_join(F.filter(lines, lambda x, i: ~F.array_contains(drop, i)), "\n")


def deduplicated(docs: DataFrame, edits: int = 2, least: int = 20) -> DataFrame:
    """doc (the row's columns), doc_id, text, n_lines, n_exact, n_near and ``kept``, the text without
    dropped lines."""
    rows, drops = judged(docs, edits, least)
    empty = F.array().cast("array<int>")
    out = rows.join(drops, "row_key", "left").withColumns({"exact": F.coalesce("exact", empty), "near": F.coalesce("near", empty), "lines": F.split("text", "\n")})
    out = out.withColumns({
        "n_lines": F.when(F.col("text").isNull(), 0).otherwise(F.size("lines")).cast("long"), "n_exact": F.size("exact").cast("long"), "n_near": F.size("near").cast("long"),
        "kept": F.when(F.size("exact") + F.size("near") == 0, F.col("text")).otherwise(_kept(F.col("lines"), F.concat("exact", "near"))),
    })
    return out.drop("row_key", "exact", "near", "lines")


def without_repeats(docs: DataFrame) -> DataFrame:
    """``docs`` with repeated lines gone; a document that loses all it said goes too."""
    same = F.col("n_exact") + F.col("n_near") == 0
    out = deduplicated(docs).filter(same | (F.trim("kept") != ""))
    changed = {"text": F.col("kept")}
    if "n_chars" in docs.columns:
        changed["n_chars"] = F.when(same, F.col("doc.n_chars")).otherwise(F.length("kept").cast(dict(docs.dtypes)["n_chars"]))
    return common.unwrapped(out, docs, **changed)


def distance(a: str, b: str) -> int:
    """Edit distance by the full matrix, for tests."""
    row = list(range(len(b) + 1))
    for i, x in enumerate(a, 1):
        back, row[0] = row[0], i
        for j, y in enumerate(b, 1):
            back, row[j] = row[j], min(row[j] + 1, row[j - 1] + 1, back + (x != y))
    return row[-1]


def brute(docs: list[tuple[int, str | None]], edits: int = 2, least: int = 20) -> dict[int, tuple[int, int, int]]:
    """n_lines, n_exact, n_near by comparing all pairs of lines, for tests."""
    first: dict[str, tuple[int, int]] = {}
    out = {d: [len(s.split("\n")) if s is not None else 0, 0, 0] for d, s in docs}
    for d, s in sorted(docs):
        for k, x in enumerate((s or "").split("\n")):
            x = x.strip(_TRIM)
            if len(x) >= least:
                out[d][1] += x in first
                first.setdefault(x, (d, k))
    up = {x: x for x in first}

    def root(x: str) -> str:
        while up[x] != x:
            x = up[x]
        return x

    lines = sorted(first, key=first.get)
    for k, x in enumerate(lines):
        for y in lines[:k]:
            if abs(len(x) - len(y)) <= edits and distance(x, y) <= edits:
                a, b = sorted((root(x), root(y)), key=first.get)
                up[b] = a
    for x in lines:
        out[first[x][0]][2] += root(x) != x
    return {d: tuple(v) for d, v in out.items()}
