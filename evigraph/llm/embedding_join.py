"""Epsilon grid order join of embeddings.

Vectors with equal labels are compared by cosine. Equal vectors become one point with a count. Points
are turned to the leading principal axes and sorted by the grid cells, of side epsilon, on them: the
epsilon grid order. Runs of the sorted sequence are blocks; two blocks are joined only if their bounding
boxes on the principal axes come within epsilon, and inside a pair of blocks the intervals are halved
and skipped by the same bound until they are small, then compared exactly. Turning is a rotation and
dropping axes only shortens distances, so no skipped pair can be within epsilon; the principal axes
come from a bounded sample and affect cost alone.

A block pair gives, per point, the number of vectors linked and one star of links per connected part,
so what leaves it is linear in its points however dense it is.

Cosines may lie exactly at the limit: such pairs link. Extra columns are ignored.

Defined results: vectors that are null, zero, or hold null or non-finite components, and rows with a
null label, link with nothing and are their own component; vectors of other lengths are only compared
with those of their own; repeated vec_ids count as vectors of their own and share a component; a null
vec_id has a null component; an empty table gives no rows.
"""

from __future__ import annotations

from collections.abc import Iterator

import numpy as np
import pyarrow as pa
import pyarrow.compute as pc
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from evigraph.llm import common

#: Points of a block, principal axes kept, axes of the block grid, rows sampled for the axes.
BLOCK, AXES, SAMPLE, LEAF = 2048, 16, 20_000, 256


def axes(points: DataFrame) -> np.ndarray:
    """Leading principal axes of about ``SAMPLE`` points, those of the least hashes, of the commonest
    length."""
    share = SAMPLE / max(1, points.count())
    some = points if share >= 1 else points.filter(F.xxhash64("vector") < int(-(1 << 63) + share * (1 << 64)))
    rows = some.select("vector").toPandas()["vector"].tolist()
    if not rows:
        return np.zeros((0, 0))
    size = max({len(r) for r in rows}, key=[len(r) for r in rows].count)
    x = np.stack([np.frombuffer(r, np.float64) for r in rows if len(r) == size])
    x = x / np.linalg.norm(x, axis=1, keepdims=True)
    _, vectors = np.linalg.eigh(np.cov(x.T) if len(x) > 1 else np.eye(x.shape[1]))
    return vectors[:, ::-1][:, :AXES]


def _rows(vectors: pa.Array) -> tuple[np.ndarray, np.ndarray, np.ndarray]:
    """Components of a list column end to end, the bounds of its rows in them, and which rows can link:
    not null or empty, all components finite, one at least not zero."""
    n = len(vectors)
    valid = np.asarray(vectors.is_valid())
    lists = vectors.cast(pa.large_list(pa.float64()))
    size = np.where(valid, np.nan_to_num(np.asarray(lists.value_lengths().fill_null(0), float)).astype(np.int64), 0)
    bounds = np.concatenate([[0], np.cumsum(size)])
    flat = lists.flatten()
    x = flat.to_numpy(zero_copy_only=False).astype(np.float64)  # a null component becomes nan
    count = lambda mask: np.diff(np.concatenate([[0], np.cumsum(mask)])[bounds])
    ok = valid & (size > 0) & (count(~np.isfinite(x)) == 0) & (count(x != 0) > 0) if n else np.zeros(0, bool)
    return x, bounds, ok


def _points(vectors: DataFrame) -> DataFrame:
    """vec_id, label, vector (its components as bytes; null if it can't link). Vectors are scaled by the
    power of two that brings their largest component near 1: exact, and no square leaves the doubles."""
    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in batches:
            x, bounds, ok = _rows(batch.column("embedding"))
            ok &= np.asarray(batch.column("label").is_valid())
            size = np.where(ok, np.diff(bounds), 0)
            owner = np.repeat(np.arange(len(ok)), np.diff(bounds))
            x, owner = x[ok[owner]], owner[ok[owner]]
            high = np.zeros(len(ok))
            np.maximum.at(high, owner, np.abs(x))
            x = np.ldexp(x, -np.frexp(high)[1][owner]) + 0.0  # no negative zero
            at = np.concatenate([[0], np.cumsum(size * 8)]).astype(np.int64)
            binary = pa.Array.from_buffers(pa.large_binary(), len(ok), [pa.py_buffer(np.packbits(ok, bitorder="little").tobytes()), pa.py_buffer(at.tobytes()), pa.py_buffer(x.tobytes())])
            yield pa.RecordBatch.from_arrays([batch.column("vec_id"), batch.column("label"), binary.cast(pa.binary())], names=["vec_id", "label", "vector"])

    kinds = dict(vectors.dtypes)
    return vectors.select("vec_id", "label", "embedding").mapInArrow(run, f"vec_id {kinds['vec_id']}, label {kinds['label']}, vector binary")


def _unit(x: np.ndarray) -> np.ndarray:
    x = x / np.abs(x).max(axis=1, keepdims=True)
    return x / np.linalg.norm(x, axis=1, keepdims=True)


def _turned(x: np.ndarray, turn: np.ndarray) -> np.ndarray:
    if turn.shape[0] == x.shape[1]:
        return _unit(x) @ turn
    return np.zeros((len(x), AXES))  # a length of its own: one cell


def _blocks(points: DataFrame, turn: np.ndarray, eps: float) -> DataFrame:
    """Blocks of the epsilon grid order: block, label, size of vectors, ids, counts, vectors, box."""
    depth = min(4, turn.shape[1]) if turn.size else 0

    def place(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in batches:
            vector = batch.column("vector")
            size = pc.binary_length(vector).to_numpy(zero_copy_only=False)
            cells = np.zeros((len(size), depth), np.int32)
            for length in np.unique(size):
                own = np.flatnonzero(size == length)
                x = np.frombuffer(b"".join(vector.take(pa.array(own)).to_pylist()), np.float64).reshape(len(own), -1)
                cells[own] = np.floor(_turned(x, turn)[:, :depth] / eps).astype(np.int32)
            lists = pa.ListArray.from_arrays(pa.array(np.arange(0, depth * len(size) + 1, depth or 1, dtype=np.int32)[: len(size) + 1] if depth else np.zeros(len(size) + 1, np.int32)), pa.array(cells.ravel()))
            yield pa.RecordBatch.from_arrays([*batch.columns, lists], names=[*batch.schema.names, "cell"])

    kinds = dict(points.dtypes)
    placed = points.mapInArrow(place, f"point long, label {kinds['label']}, vector binary, n long, cell array<int>")
    ordered = placed.withColumn("length", F.length("vector")).repartitionByRange("label", "length", "cell", "point").sortWithinPartitions("label", "length", "cell", "point")

    def cut(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        held: list[tuple] = []

        def block(rows: list[tuple]) -> pa.RecordBatch:
            x = np.stack([np.frombuffer(r[2], np.float64) for r in rows])
            y = _turned(x, turn)
            return pa.RecordBatch.from_arrays([
                pa.array([min(r[0] for r in rows)]), pa.array([rows[0][1]], kind), pa.array([x.shape[1]], pa.int32()), pa.array([np.array([r[0] for r in rows], np.int64).tobytes()]),
                pa.array([np.array([r[3] for r in rows], np.int64).tobytes()]), pa.array([x.tobytes()]), pa.array([y.min(axis=0).tolist()]), pa.array([y.max(axis=0).tolist()]),
            ], names=["block", "label", "size", "ids", "counts", "vectors", "low", "high"])

        kind = None
        for batch in batches:
            kind = batch.schema.field("label").type
            for r in zip(*(batch.column(c).to_pylist() for c in ("point", "label", "vector", "n")), strict=True):
                if held and (len(held) >= BLOCK or held[-1][1] != r[1] or len(held[-1][2]) != len(r[2])):
                    yield block(held)
                    held = []
                held.append(r)
        if held:
            yield block(held)

    return ordered.mapInArrow(cut, f"block long, label {kinds['label']}, size int, ids binary, counts binary, vectors binary, low array<double>, high array<double>")


def _near(a: tuple[np.ndarray, np.ndarray], b: tuple[np.ndarray, np.ndarray], eps: float) -> bool:
    gap = np.maximum(0, np.maximum(a[0] - b[1], b[0] - a[1]))
    return float(gap @ gap) <= eps * eps * (1 + 1e-9) + 1e-12


def _join(x, y, least: float, eps: float, same: bool, turn: np.ndarray) -> tuple[np.ndarray, np.ndarray]:
    """Index pairs of two blocks with cosine >= least, by halving intervals of the grid order."""
    ux, uy = _unit(x), _unit(y)
    tx, ty = _turned(x, turn), _turned(y, turn)
    out_a, out_b = [], []
    todo = [(0, len(x), 0, len(y))]
    while todo:
        a, b, c, d = todo.pop()
        if same and c < a:
            continue  # the mirror image is joined
        if not _near((tx[a:b].min(axis=0), tx[a:b].max(axis=0)), (ty[c:d].min(axis=0), ty[c:d].max(axis=0)), eps):
            continue
        if b - a > LEAF or d - c > LEAF:
            cuts_a = [a, (a + b) // 2, b] if b - a > LEAF else [a, b]
            cuts_c = [c, (c + d) // 2, d] if d - c > LEAF else [c, d]
            todo += [(a1, b1, c1, d1) for a1, b1 in zip(cuts_a, cuts_a[1:], strict=False) for c1, d1 in zip(cuts_c, cuts_c[1:], strict=False)]
            continue
        i, j = np.nonzero(ux[a:b] @ uy[c:d].T >= least - 1e-9)
        i, j = i + a, j + c
        if same:
            i, j = i[i < j], j[i < j]
        # the limit itself by the plain formula in double precision
        p, q = x[i], y[j]
        exact = (p * q).sum(axis=1) / (np.sqrt((p * p).sum(axis=1)) * np.sqrt((q * q).sum(axis=1)))
        out_a.append(i[exact >= least])
        out_b.append(j[exact >= least])
    return np.concatenate(out_a or [np.zeros(0, np.int64)]), np.concatenate(out_b or [np.zeros(0, np.int64)])


def _lowest(n: int, a: np.ndarray, b: np.ndarray) -> np.ndarray:
    """The least index connected to each of n, for undirected links."""
    low = np.arange(n)
    while len(a):
        before = low.copy()
        np.minimum.at(low, a, low[b])
        np.minimum.at(low, b, low[a])
        low = low[low]
        if (low == before).all():
            break
    return low


def _met(pairs: DataFrame, least: float, eps: float, turn: np.ndarray) -> DataFrame:
    """(point, other, n): with other null, n vectors linked to the point; else a link of a star."""
    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in batches:
            for row in batch.to_pylist():
                ia, ib = np.frombuffer(row["ids"], np.int64), np.frombuffer(row["ids2"], np.int64)
                na, nb = np.frombuffer(row["counts"], np.int64), np.frombuffer(row["counts2"], np.int64)
                x, y = (np.frombuffer(row[c], np.float64).reshape(-1, row["size"]) for c in ("vectors", "vectors2"))
                same = row["block"] == row["block2"]
                a, b = _join(x, y, least, eps, same, turn)
                if not len(a):
                    continue
                point = np.concatenate([ia[a], ib[b]])
                u, inverse = np.unique(point, return_inverse=True)
                links = np.bincount(inverse, weights=np.concatenate([nb[b], na[a]]), minlength=len(u)).astype(np.int64)
                low = _lowest(len(u), np.searchsorted(u, ia[a]), np.searchsorted(u, ib[b]))
                own = np.flatnonzero(low != np.arange(len(u)))
                yield pa.RecordBatch.from_arrays([
                    pa.array(np.concatenate([u, u[own]])), pa.array(np.concatenate([np.zeros(len(u), np.int64), u[low[own]]]), mask=np.arange(len(u) + len(own)) < len(u)),
                    pa.array(np.concatenate([links, np.zeros(len(own), np.int64)])),
                ], names=["point", "other", "n"])

    return pairs.mapInArrow(run, "point long, other long, n long")


def join(vectors: DataFrame, least: float = 0.98) -> DataFrame:
    """vec_id, n_links, component_id, kept of every vector."""
    eps = float(np.sqrt(2 - 2 * least)) * (1 + 1e-6) + 1e-7
    rows = common.written(_points(vectors))
    points = rows.filter("vector is not null and vec_id is not null").groupBy("label", "vector").agg(F.min("vec_id").alias("point"), F.count("*").alias("n"))
    points = common.written(points.select(F.col("point").cast("long").alias("point"), "label", "vector", "n"))
    # a repeated vec_id may stand for several vectors: each point needs a number of its own
    twice = points.groupBy("point").agg(F.count("*").alias("c")).filter("c > 1")
    clash = points.join(twice, "point", "left_semi")
    number = F.coalesce(F.when(F.col("clash"), -F.abs(F.xxhash64("label", "vector")) - 1), F.col("point"))
    points = common.written(
        points.join(clash.select("point").distinct().withColumn("clash", F.lit(True)), "point", "left").withColumn("id", F.col("point")).withColumn("point", number).select("point", "label", "vector", "n", "id")
    )
    turn = axes(points)
    blocks = common.written(_blocks(points.select("point", "label", "vector", "n"), turn, eps))
    boxes = blocks.select("block", "label", "size", "low", "high")
    # blocks meet in the first cell of the two leading axes that both span or touch, so each pair meets once
    cell = lambda c, k, off: F.floor((F.coalesce(F.get(c, F.lit(k)), F.lit(0.0)) + off) / eps).cast("long")

    def spread(df: DataFrame, end: str, off: float) -> DataFrame:
        for k in (0, 1):
            df = df.withColumn(f"from{k}{end}", cell(f"low{end}", k, -off)).withColumn(f"cell{k}", F.explode(F.sequence(F.col(f"from{k}{end}"), cell(f"high{end}", k, off))))
        return df

    left = spread(boxes, "", 0.0)
    right = spread(boxes.select("label", "size", *(F.col(c).alias(f"{c}2") for c in ("block", "low", "high"))), "2", eps)
    gap = F.aggregate(F.zip_with(F.zip_with("low", "high2", lambda a, b: a - b), F.zip_with("low2", "high", lambda a, b: a - b), lambda a, b: F.greatest(a, b, F.lit(0.0))), F.lit(0.0), lambda s, g: s + g * g)
    near = left.join(right, ["label", "size", "cell0", "cell1"]).filter((F.col("block") <= F.col("block2")) & (F.col("cell0") == F.greatest("from0", "from02")) & (F.col("cell1") == F.greatest("from1", "from12")))
    near = near.filter(gap <= eps * eps * (1 + 1e-9) + 1e-12).select("block", "block2")
    full = blocks.select("block", "size", "ids", "counts", "vectors")
    other = full.select(*(F.col(c).alias(f"{c}2") for c in ("block", "ids", "counts", "vectors")))
    # a few pairs to a task: comparing is what takes time
    pairs = near.repartition("block", "block2").join(full, "block").join(other, "block2")
    met = common.written(_met(pairs, least, eps, turn))
    counts = met.filter("other is null").groupBy("point").agg(F.sum("n").alias("m"))
    parts = common.components(met.filter("other is not null").select(F.col("point").alias("a"), F.col("other").alias("b"))).withColumnRenamed("id", "point")
    named = points.join(counts, "point", "left").join(parts, "point", "left").withColumn("part", F.coalesce("component_id", "point"))
    linked = rows.filter("vec_id is not null").join(named.select("label", "vector", "n", "m", "part"), ["label", "vector"], "left").select(
        "vec_id", "part", F.when(F.col("n").isNull(), 0).otherwise(F.col("n") - 1 + F.coalesce("m", F.lit(0))).cast("long").alias("n_links")
    )
    linked = common.written(linked)
    lowest = linked.filter("part is not null").groupBy("part").agg(F.min("vec_id").alias("low"))
    out = linked.join(lowest, "part", "left").select("vec_id", "n_links", F.coalesce("low", "vec_id").alias("component_id"))
    out = out.withColumn("kept", F.col("vec_id") == F.col("component_id"))
    lost = rows.filter("vec_id is null").select("vec_id", F.lit(0).cast("long").alias("n_links"), F.col("vec_id").alias("component_id"), F.lit(False).alias("kept"))
    return out.unionByName(lost)


def brute(rows: list[tuple[int, list[float] | None, int | None]], least: float = 0.98) -> dict[int, tuple[int, int, bool]]:
    ok = [(i, np.array(v, np.float64), lab) for i, v, lab in rows if lab is not None and v and None not in v and np.isfinite(v).all() and np.any(v)]
    links: dict[int, set[int]] = {i: set() for i, _, _ in rows}
    for lab in {r[2] for r in ok}:
        own = [r for r in ok if r[2] == lab]
        x = np.stack([r[1] for r in own])
        u = x / np.linalg.norm(x, axis=1, keepdims=True)
        for a, b in zip(*np.nonzero(u @ u.T >= least), strict=True):
            if a != b:
                links[own[a][0]].add(own[b][0])
    seen: dict[int, int] = {}
    for i in sorted(links):
        todo = [i]
        while todo:
            k = todo.pop()
            if k not in seen:
                seen[k] = i
                todo += links[k]
    return {i: (len(links[i]), seen[i], seen[i] == i) for i in links}
