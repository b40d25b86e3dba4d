"""Language identification by rank-order profiles.

A profile is the list of the most frequent character n-grams (1 to 3 letters, words padded by a
space), most frequent first. Each n-gram is packed exactly into one integer, 21 bits a character.
Language profiles are counted over all learning documents and cut to ``PROFILE`` n-grams; a document's
profile over its whole text is compared with each by the out-of-place distance: the sum, over the
document's n-grams, of the difference of ranks, or of ``PROFILE`` for one that the language lacks.

All languages of the learning rows get a profile. Texts of any length are counted whole; extra columns are
carried along.

Defined results: null text, or a text without a letter, gives ``und`` with score 0, as does an empty
model; ties go to the language under which the n-grams have the higher mean log frequency, then to the
smaller name; rows with a null lang teach nothing; repeated rows are judged alike.
"""

from __future__ import annotations

import sys
from collections.abc import Iterator
from dataclasses import dataclass

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame, Window
from pyspark.sql import functions as F

from evigraph.llm import common, text

#: N-grams of a language's profile, of a document's, and n at most.
PROFILE, OWN, LONGEST = 400, 400, 3
_U = np.uint64
_TABLE: np.ndarray | None = None


def _letters() -> np.ndarray:
    """Lower-cased letter of each code point; 0 for what is no letter."""
    global _TABLE
    if _TABLE is None:
        _TABLE = np.zeros(sys.maxunicode + 1, np.uint32)
        for c in range(sys.maxunicode + 1):
            x = chr(c)
            if x.isalpha():
                low = x.lower()
                _TABLE[c] = ord(low) if len(low) == 1 else c
    return _TABLE


@dataclass
class Grams:
    """The distinct n-grams of each row with their counts, by row and n-gram. An n-gram is ``bits`` wide and
    has ``width`` bits a character, each the place of a letter in ``letters``; places keep the order of
    the letters, so n-grams sort as their characters do."""

    row: np.ndarray
    gram: np.ndarray
    count: np.ndarray
    has: np.ndarray
    letters: np.ndarray
    width: int

    @property
    def bits(self) -> int:
        return LONGEST * self.width

    def packed(self, gram: np.ndarray) -> np.ndarray:
        """N-grams as integers that mean the same in every slice: 21 bits a character."""
        out = np.zeros(len(gram), _U)
        for k in range(LONGEST):
            place = (gram >> _U((LONGEST - 1 - k) * self.width)) & _U((1 << self.width) - 1)
            out = out << _U(21) | self.letters[place]
        return out


def grams(body: pa.Array, group: np.ndarray | None = None) -> Grams:
    """N-grams of the texts of a column; ``group`` gives rows a number under which they are counted
    together. Rows without letters have none."""
    data, at = text.points(*common.raw(body))
    n = len(at) - 1
    keep = np.flatnonzero(_letters()[data])
    row = np.searchsorted(at, keep, side="right") - 1
    low = _letters()[data[keep]]
    known = np.zeros(sys.maxunicode + 1, np.uint32)
    known[low] = 1
    letters = np.flatnonzero(known)
    width = int(len(letters) + 1).bit_length()
    known[letters] = np.arange(2, len(letters) + 2)  # 0 is nothing, 1 the gap between words
    has = np.zeros(n, bool)
    has[row] = True
    owner = row if group is None else group[row]
    # a word starts where the letter before is not next to it or is of another row; a gap goes before each
    start = np.ones(len(keep), bool)
    start[1:] = (np.diff(keep) > 1) | (np.diff(row) > 0)
    place = np.cumsum(start) + np.arange(len(keep))
    size = int(place[-1]) + 2 if len(keep) else 0
    c, own = np.ones(size, _U), np.zeros(size, _U)
    c[place], own[place] = known[low], owner
    gap = np.ones(size, bool)
    gap[place] = False
    own[:-1][gap[:-1]] = own[1:][gap[:-1]]
    own = own << _U(LONGEST * width)
    # an n-gram that ends on the next word's gap belongs to the word it starts in
    two = own[:-1] | c[:-1] << _U(width) | c[1:] if size else own
    keys = [(own | c)[~gap], two]
    if size > 2:
        whole = ~gap[1:-1]
        keys.append((two[:-1] << _U(width) | c[2:])[whole] & _U((1 << LONGEST * width) - 1) | own[:-2][whole])
    key = np.sort(np.concatenate(keys))
    new = np.flatnonzero(np.append(True, key[1:] != key[:-1])) if len(key) else np.zeros(0, np.int64)
    count = np.diff(np.append(new, len(key)))
    key = key[new]
    return Grams((key >> _U(LONGEST * width)).astype(np.int64), key & _U((1 << LONGEST * width) - 1), count, has, np.concatenate([[0, 0x20], letters]).astype(_U), width)


def ranked(g: Grams, most: int) -> tuple[np.ndarray, np.ndarray, np.ndarray, np.ndarray]:
    """(row, packed n-gram, count, rank from 0) of the most frequent n-grams of each row; ties by n-gram."""
    if not len(g.row):
        return g.row, g.gram, g.count, g.row
    high = int(g.count.max())
    room = high.bit_length()
    if int(g.row.max()).bit_length() + room + g.bits <= 64:
        key = np.sort((g.row.astype(_U) << _U(room) | (high - g.count).astype(_U)) << _U(g.bits) | g.gram)
        row, count, gram = (key >> _U(g.bits + room)).astype(np.int64), high - ((key >> _U(g.bits)) & _U((1 << room) - 1)).astype(np.int64), key & _U((1 << g.bits) - 1)
    else:
        order = np.lexsort((g.gram, -g.count, g.row))
        row, count, gram = g.row[order], g.count[order], g.gram[order]
    new = np.append(True, row[1:] != row[:-1])
    rank = np.arange(len(row)) - np.flatnonzero(new)[np.cumsum(new) - 1]
    top = rank < most
    return row[top], g.packed(gram[top]), count[top], rank[top]


def _slices(batch: pa.RecordBatch) -> Iterator[pa.RecordBatch]:
    """Slices whose rows can be numbered beside an n-gram in 64 bits."""
    for part in common.slices(batch, "text"):
        for k in range(0, len(part), 4096):
            yield part.slice(k, 4096)


def profiles(docs: DataFrame) -> dict[str, list[tuple[int, float]]]:
    """The profile of every language: its n-grams by rank with log frequencies."""
    def count(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in batches:
            for part in _slices(batch):
                code = part.column("lang").dictionary_encode()
                g = grams(part.column("text"), code.indices.to_numpy(zero_copy_only=False).astype(np.int64))
                if len(g.row):
                    yield pa.RecordBatch.from_arrays([code.dictionary.take(pa.array(g.row)), pa.array(g.packed(g.gram).view(np.int64)), pa.array(g.count)], names=["lang", "g", "n"])

    learn = docs.filter("lang is not null and text is not null").select("lang", "text")
    sums = learn.mapInArrow(count, "lang string, g long, n long").groupBy("lang", "g").agg(F.sum("n").alias("n"))
    sums = common.written(sums)
    total = sums.groupBy("lang").agg(F.sum("n").alias("total"))
    best = sums.withColumn("rank", F.row_number().over(Window.partitionBy("lang").orderBy(F.desc("n"), "g"))).filter(F.col("rank") <= PROFILE).join(total, "lang")
    out: dict[str, list[tuple[int, float]]] = {}
    for x in best.orderBy("lang", "rank").collect():
        out.setdefault(x["lang"], []).append((x["g"], float(np.log(x["n"] / x["total"]))))
    return out


def predicted(docs: DataFrame, model: dict[str, list[tuple[int, float]]]) -> DataFrame:
    """``docs`` without text, with lang_pred and score: how much smaller the best distance is than the
    second, as a share of the second (1 where only one language is known)."""
    names = sorted(model)
    every = np.unique(np.array([g for p in model.values() for g, _ in p], np.int64).view(_U)) if names else np.zeros(0, _U)
    rank_of = np.full((len(every) + 1, len(names)), -1, np.int64)
    log_of = np.full((len(every) + 1, len(names)), -20.0)
    for k, name in enumerate(names):
        at = np.searchsorted(every, np.array([g for g, _ in model[name]], np.int64).view(_U))
        rank_of[at, k] = np.arange(len(at))
        log_of[at, k] = [x for _, x in model[name]]

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in batches:
            for part in _slices(batch):
                n = len(part)
                found = grams(part.column("text"))
                best, score = np.full(n, "und", object), np.zeros(n)
                if names:
                    r, g, count, rank = ranked(found, OWN)
                    at = np.minimum(np.searchsorted(every, g), len(every) - 1)
                    at = np.where(every[at] == g, at, len(every))
                    far, mean = np.zeros((n, len(names))), np.zeros((n, len(names)))
                    for k in range(len(names)):
                        place = rank_of[at, k]
                        far[:, k] = np.bincount(r, weights=np.where(place < 0, PROFILE, np.abs(rank - place)), minlength=n)
                        mean[:, k] = np.bincount(r, weights=log_of[at, k] * count, minlength=n)
                    least = far.min(axis=1)
                    first = np.argmax(np.where(far == least[:, None], mean, -np.inf), axis=1)
                    second = np.partition(far, 1, axis=1)[:, 1] if len(names) > 1 else np.full(n, np.inf)
                    has = found.has
                    best[has] = np.array(names, object)[first[has]]
                    score[has] = np.where(second > 0, 1 - least / np.where(second > 0, second, 1), 0.0)[has]
                keep = [k for k in range(part.num_columns) if part.schema.names[k] != "text"]
                yield pa.RecordBatch.from_arrays([*(part.column(k) for k in keep), pa.array(best, pa.string()), pa.array(score)], names=[*(part.schema.names[k] for k in keep), "lang_pred", "score"])

    return docs.mapInArrow(run, common.with_fields(docs, ("text",), lang_pred="string", score="double"))


def remainder(column: str, n: int):
    return F.coalesce(F.pmod(F.crc32(F.col(column).cast("string").cast("binary")), F.lit(n)), F.lit(-1))
