"""Benchmark decontamination by a positional inverted index.

The index is partitioned by document: each slice of the corpus keeps, for the terms that the
benchmark has, the sorted positions at which they stand. A phrase is looked up in every slice by
intersecting position lists, each moved back by the term's place in the phrase, from the phrase's
rarest term in that slice to its commonest. No posting is shuffled; only the benchmark travels, as
numbers of its terms in text order, a phrase being a place in them. :func:`stored` keeps the index of all
terms as a table for benchmarks to come, and :func:`searched` asks it.

Defined results: null or empty text has no words and no hits; repeated rows each give a row; items
without words or without an id match nothing, rows that share an item_id count as one item; an empty
benchmark or corpus gives zero hits or no rows; further columns of the inputs are ignored.
"""

from __future__ import annotations

import hashlib
from collections.abc import Iterator
from dataclasses import dataclass

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from evigraph.llm import common, text

#: Benchmark text that goes to every task at once; a larger benchmark is matched in blocks of items.
BLOCK_BYTES = 8_000_000
#: Phrases looked up at once.
CHUNK = 100_000


@dataclass
class Phrases:
    """Phrases over a vocabulary of term hashes: each a begin and a length in the benchmark's terms in
    text order, and the number of its item."""

    vocabulary: np.ndarray
    flat: np.ndarray
    begin: np.ndarray
    length: np.ndarray
    item: np.ndarray
    names: list[str]

    @classmethod
    def of(cls, rows: list[tuple[str, str]], size: int) -> Phrases:
        w = text.words(*common.raw(pa.array([body for _, body in rows], pa.string())), text.ALNUM)
        vocabulary, flat = np.unique(w.hashes, return_inverse=True)
        n = np.diff(w.bounds)
        count = np.where(n >= size, n - size + 1, np.minimum(n, 1))
        row = np.repeat(np.arange(len(n)), count)
        begin = w.bounds[:-1][row] + np.arange(len(row)) - np.repeat(np.cumsum(count) - count, count)
        names = sorted({item for item, _ in rows})
        at = {name: k for k, name in enumerate(names)}
        number = np.array([at[item] for item, _ in rows], np.int32)
        return cls(vocabulary, flat.astype(np.int32), begin, np.minimum(n, size)[row].astype(np.int32), number[row], names)

    def terms(self, which: np.ndarray) -> np.ndarray:
        """phrase x place: the term, -1 past the phrase's end."""
        place = np.arange(int(self.length.max(initial=1)))
        inside = place < self.length[which][:, None]
        return np.where(inside, self.flat[np.where(inside, self.begin[which][:, None] + place, 0)], -1)


class Shard:
    """The positional index of one slice of documents, over the terms of ``vocabulary``."""

    def __init__(self, words: text.Words, vocabulary: np.ndarray):
        self.bounds = words.bounds
        at = np.searchsorted(vocabulary, words.hashes)
        at[at == len(vocabulary)] = 0
        self.term_at = np.where(vocabulary[at] == words.hashes, at, -1) if len(vocabulary) else np.full(len(at), -1)
        known = np.flatnonzero(self.term_at >= 0)
        terms = self.term_at[known]
        self.postings = known[np.argsort(terms, kind="stable")]
        self.counts = np.bincount(terms, minlength=len(vocabulary))
        self.starts = np.concatenate([[0], np.cumsum(self.counts)])

    def listed(self, term: np.ndarray) -> tuple[np.ndarray, np.ndarray]:
        """Positions of each asked term, end to end, and which entry of ``term`` each belongs to."""
        n = self.counts[term]
        which = np.repeat(np.arange(len(term)), n)
        return self.postings[np.repeat(self.starts[term] - np.cumsum(n) + n, n) + np.arange(n.sum())], which

    def _live(self, p: Phrases):
        """(phrases, their terms, counts of these) of which every term stands in the slice, in chunks."""
        for a in range(0, len(p.begin), CHUNK):
            which = np.arange(a, min(a + CHUNK, len(p.begin)))
            terms = p.terms(which)
            counts = np.where(terms >= 0, self.counts[terms], np.iinfo(np.int64).max)
            live = np.flatnonzero(counts.min(axis=1) > 0)
            if len(live):
                yield which[live], terms[live], counts[live]

    def phrases(self, p: Phrases) -> tuple[np.ndarray, np.ndarray]:
        """(first position, phrase) of every exact occurrence that stays inside a document."""
        out = [(np.zeros(0, np.int64), np.zeros(0, np.int64))]
        for live, terms, counts in self._live(p):
            by_rarity = np.argsort(counts, axis=1, kind="stable")
            rarest = by_rarity[:, 0]
            at, which = self.listed(terms[np.arange(len(live)), rarest])
            at = at - rarest[which]
            ends = at + p.length[live[which]]
            row = np.searchsorted(self.bounds, np.maximum(at, 0), side="right") - 1
            ok = (at >= 0) & (at >= self.bounds[row]) & (ends <= self.bounds[np.minimum(row + 1, len(self.bounds) - 1)])
            at, which = at[ok], which[ok]
            for k in range(1, terms.shape[1]):
                place = by_rarity[which, k]
                term = terms[which, place]
                past = term < 0
                same = past | (self.term_at[np.where(past, 0, at + place)] == term)
                at, which = at[same], which[same]
            out.append((at, live[which]))
        return tuple(np.concatenate(x) for x in zip(*out, strict=True))

    def near(self, p: Phrases, slop: int) -> tuple[np.ndarray, np.ndarray]:
        """(position of the rarest term, phrase) where all other terms of the phrase stand within
        ``slop`` words of their exact place, in the same document."""
        out = [(np.zeros(0, np.int64), np.zeros(0, np.int64))]
        for live, terms, counts in self._live(p):
            by_rarity = np.argsort(counts, axis=1, kind="stable")
            rarest = by_rarity[:, 0]
            at, which = self.listed(terms[np.arange(len(live)), rarest])
            row = np.searchsorted(self.bounds, at, side="right") - 1
            low, high = self.bounds[row], self.bounds[row + 1]
            for k in range(1, terms.shape[1]):
                place = by_rarity[which, k]
                term = terms[which, place]
                found = term < 0
                for move in range(-slop, slop + 1):
                    where = at + place - rarest[which] + move
                    inside = (where >= low) & (where < high)
                    found |= inside & (self.term_at[np.where(inside, where, 0)] == term)
                at, which, low, high = at[found], which[found], low[found], high[found]
            out.append((at, live[which]))
        return tuple(np.concatenate(x) for x in zip(*out, strict=True))


def _blocks(bench: DataFrame, limit: int) -> list[DataFrame]:
    rows = bench.filter("item_id is not null and text is not null").select(F.col("item_id").cast("string").alias("item_id"), "text")
    total = rows.agg(F.sum(F.octet_length("text")).alias("b")).first()["b"] or 0
    n = max(1, -(-total // limit))
    return [rows.filter(F.pmod(F.xxhash64("item_id"), F.lit(n)) == k) if n > 1 else rows for k in range(n)]


def _matcher(phrases: Phrases, slop: int | None, dropped: tuple[str, ...]):
    """Adds n_words, the hit word places of each row and the items found to each batch."""

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in batches:
            for part in common.slices(batch, "text"):
                w = text.words(*common.raw(part.column("text")), text.ALNUM)
                n = len(w.bounds) - 1
                hits: list[list[int]] = [[] for _ in range(n)]
                items: list[list[str]] = [[] for _ in range(n)]
                if len(phrases.begin) and len(w.hashes):
                    shard = Shard(w, phrases.vocabulary)
                    if slop is None:
                        at, which = shard.phrases(phrases)
                        lengths = phrases.length[which]
                    else:
                        at, which = shard.near(phrases, slop)
                        lengths = np.ones(len(at), np.int64)
                    marks = np.zeros(len(w.hashes) + 1, np.int64)
                    np.add.at(marks, at, 1)
                    np.add.at(marks, at + lengths, -1)
                    hit = np.flatnonzero(np.cumsum(marks[:-1]) > 0)
                    rows = np.searchsorted(w.bounds, hit, side="right") - 1
                    some, first = np.unique(rows, return_index=True)
                    for r, a, b in zip(some, first, np.append(first, len(rows))[1:], strict=True):
                        hits[r] = (hit[a:b] - w.bounds[r]).tolist()
                    pairs = np.unique((np.searchsorted(w.bounds, at, side="right") - 1) * len(phrases.names) + phrases.item[which])
                    for r, i in zip(pairs // len(phrases.names), pairs % len(phrases.names), strict=True):
                        items[r].append(phrases.names[i])
                out = [part.column(k) for k in range(part.num_columns) if part.schema.names[k] not in dropped]
                names = [k for k in part.schema.names if k not in dropped]
                out += [pa.array(np.diff(w.bounds)), pa.array(hits, pa.list_(pa.int32())), pa.array([sorted(set(x)) for x in items], pa.list_(pa.string()))]
                yield pa.RecordBatch.from_arrays(out, names=[*names, "n_words", "hit", "items"])

    return run


def matches(docs: DataFrame, bench: DataFrame, keep: list[str], window: int = 13, slop: int | None = None, block_bytes: int = BLOCK_BYTES) -> DataFrame:
    """The columns ``keep`` of each row of ``docs`` with n_words, the places of words hit (``hit``)
    and the sorted ids of the items found (``items``). ``slop`` asks for proximity in place of exact
    phrases. A benchmark beyond ``block_bytes`` is matched in blocks whose results are united."""
    blocks = _blocks(bench, block_bytes)
    dropped = () if "text" in keep else ("text",)
    asked = list(dict.fromkeys([*keep, "text"]))

    def run(source: DataFrame, block: DataFrame) -> DataFrame:
        phrases = Phrases.of([tuple(r) for r in block.collect()], window)
        return source.mapInArrow(_matcher(phrases, slop, dropped), common.with_fields(source, dropped, n_words="long", hit="array<int>", items="array<string>"))

    if len(blocks) == 1:
        return run(docs.select(*asked), blocks[0])
    rows = common.written(docs.select(*asked, F.expr("uuid()").alias("row_key")))
    parts = [run(rows, b) for b in blocks]
    united = parts[0]
    for p in parts[1:]:
        united = united.unionByName(p)
    return united.groupBy("row_key").agg(
        *(F.first(k).alias(k) for k in keep), F.first("n_words").alias("n_words"),
        F.array_distinct(F.flatten(F.collect_list("hit"))).alias("hit"), F.array_sort(F.array_distinct(F.flatten(F.collect_list("items")))).alias("items"),
    ).drop("row_key")


def stored(docs: DataFrame, key: str = "doc_id") -> DataFrame:
    """The positional index of all terms as a table in the shared folder: term hash, document, its number of
    words and the sorted positions of the term in it, dealt and sorted by term so that a scan for a few
    terms reads a few row groups."""
    kind = dict(docs.dtypes)[key]

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in batches:
            for part in common.slices(batch, "text"):
                w = text.words(*common.raw(part.column("text")), text.ALNUM)
                rows = w.rows
                order = np.lexsort((np.arange(len(rows)), w.hashes, rows))
                rows, hashes, at = rows[order], w.hashes[order], (order - w.bounds[rows[order]] if len(order) else order)
                new = np.flatnonzero(np.append(True, (rows[1:] != rows[:-1]) | (hashes[1:] != hashes[:-1])))[: len(rows)] if len(rows) else np.zeros(0, np.int64)
                lists = pa.ListArray.from_arrays(pa.array(np.append(new, len(rows)).astype(np.int32)), pa.array(at.astype(np.int32)))
                yield pa.RecordBatch.from_arrays([
                    pa.array(hashes[new].view(np.int64)), part.column(key).take(pa.array(rows[new])), pa.array(np.diff(w.bounds)[rows[new]]), lists,
                ], names=["term", "doc", "n_words", "positions"])

    rows = docs.select(key, "text").mapInArrow(run, f"term long, doc {kind}, n_words long, positions array<int>")
    return common.written(rows.repartition("term", F.pmod(F.xxhash64("doc"), F.lit(16))).sortWithinPartitions("term", "doc"))


def _back(place: int):
    return lambda p: p - place


def searched(index: DataFrame, phrase: str, slop: int = 0) -> DataFrame:
    """(doc, at) of a phrase in a stored index: the lists of its terms, from the one of fewest documents on,
    each moved back by the term's place; with ``slop`` a term may stand so many words off its place. ``at``
    is where the rarest term has the phrase begin."""
    w = text.words(*common.raw(pa.array([phrase], pa.string())), text.ALNUM).hashes.view(np.int64).tolist()
    if not w:
        return index.select("doc", F.lit(0).alias("at")).filter("false")
    own = index.filter(F.col("term").isin(*set(w)))
    held = {r["term"]: r["n"] for r in own.groupBy("term").agg(F.sum(F.size("positions")).alias("n")).collect()}
    order = sorted(range(len(w)), key=lambda k: (held.get(w[k], 0), k))
    found = None
    for k in order:
        lists = own.filter(F.col("term") == w[k]).groupBy("doc", "n_words").agg(F.array_distinct(F.flatten(F.collect_list("positions"))).alias("positions"))
        moved = F.transform("positions", _back(k))
        if found is None:
            inside = F.filter(moved, lambda p: (p >= 0) & (p + len(w) <= F.col("n_words"))) if not slop else moved
            found = lists.select("doc", inside.alias("at"))
            continue
        reach = moved if not slop else F.array_distinct(F.flatten(F.transform(moved, lambda p: F.sequence(p - slop, p + slop))))
        found = found.join(lists.select("doc", reach.alias("next")), "doc").select("doc", F.array_intersect("at", "next").alias("at")).filter(F.size("at") > 0)
    return found.select("doc", F.explode("at").alias("at"))


def judged(hits: DataFrame, share: int = 20) -> DataFrame:
    """Counts, digest of the items and verdict: contaminated if hit words are at least 1/``share``."""
    return hits.withColumns({
        "n_hit": F.size("hit").cast("long"), "n_items": F.size("items").cast("long"), "items_sha256": F.sha2(F.array_join("items", ","), 256),
    }).withColumn("contaminated", (F.col("n_hit") > 0) & (F.col("n_hit") * share >= F.col("n_words"))).drop("hit", "items")


def decontaminated(docs: DataFrame, bench: DataFrame) -> DataFrame:
    """The rows of ``docs`` (with the columns of documents) that are not contaminated."""
    hits = judged(matches(common.apart(docs), bench, ["doc", "text"]))
    return common.unwrapped(hits.filter(~F.col("contaminated")), docs, text=F.col("text"))


def brute(doc: str | None, items: list[tuple[int, str]], window: int = 13) -> dict:
    """The contract in plain Python, for tests."""
    import re

    split = lambda s: re.findall(r"[^\x00-\x2F\x3A-\x60\x7B-\x7F]+", re.sub("[A-Z]", lambda m: m[0].lower(), s or ""))
    w, hit, found = split(doc), set(), set()
    for item, body in items:
        t = split(body)
        for k in range(max(1, len(t) - window + 1) if t else 0):
            p = t[k : k + window]
            for i in range(len(w) - len(p) + 1):
                if w[i : i + len(p)] == p:
                    hit.update(range(i, i + len(p)))
                    found.add(str(item))
    return {"n_words": len(w), "n_hit": len(hit), "n_items": len(found), "items_sha256": hashlib.sha256(",".join(sorted(found)).encode()).hexdigest(), "contaminated": bool(hit) and 20 * len(hit) >= len(w)}
