"""Subword lattice language model.

The pieces of an existing subword vocabulary span a lattice over every word: an arc for each piece that
stands at a place, single bytes where no other fits. A word's probability is the sum over all ways to
cut it, each the product of its arcs' probabilities, found by the forward recursion in log space. An arc
is scored by its piece and by whether it starts and whether it ends the word, so the words need no
separator and the probabilities of all words sum to one; after each word the text ends or goes on.

The vocabulary's own scores are where the arcs' scores start; a file that only ranks its pieces is read by
the reciprocal of the rank. ``ROUNDS`` rounds of expected counts over all learning words adapt them, for
each class of learning documents (their languages) apart, held toward the scores of all classes.
Every word that the learning documents of a class hold is one more arc of its lattice, from its start to
its end, in place of nothing: its weight is the word's count, that of all other cuts the number of distinct
words (Witten-Bell). A text's probability is the mixture over classes of the products over its words,
its marginal over cuts and classes. ``piece_score`` is the same without the arcs of whole words.

Word counts are gathered from the whole corpus by shuffles; every distinct word is scored once and
joined back to the documents. The commonest words, at most ``HOT``, are added up where the documents are
read, so no common word becomes a hot key.

Defined results: null and empty text have the end token only; without learning documents counts are 0
and the base probability of a token is 1; rows equal in doc_id and text get equal results; learning
documents with a null lang form a class of their own; of more classes than ``CLASSES`` the smallest are
one class together; words and texts may be of any length; extra columns of the input are ignored.
"""

from __future__ import annotations

from collections.abc import Iterator

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from evigraph.llm import common, text

HOT, CLASSES, ROUNDS = 50_000, 16, 2
#: How many counts the scores of all classes are worth to a class, and the first scores to all classes.
HELD, FIRST = 200.0, 50.0
_U = np.uint64
_START = _U(0x5BD1E995)
#: Stands for the end token among the words; no word can hold a line feed.
END = "\n"


class Vocabulary:
    """Pieces as bytes, and whether they start a word, with log scores. The first 256 indexes are single
    bytes, the next 256 single bytes that start a word, then come the pieces of the file."""

    def __init__(self, pieces: list[tuple[bytes, bool]], logs: np.ndarray):
        self.pieces = pieces
        keys = np.array([text.hash_of(b) for b, _ in pieces], _U) ^ np.where(np.array([s for _, s in pieces], bool), _START, _U(0))
        sizes = np.array([len(b) for b, _ in pieces], np.int64)
        self.by_size: dict[int, tuple[np.ndarray, np.ndarray, np.ndarray]] = {}
        for size in np.unique(sizes).tolist():
            own = np.flatnonzero(sizes == size)
            order = own[np.argsort(keys[own])]
            may = np.zeros(1 << 16, bool)
            may[(keys[order] >> _U(48)).astype(np.int64)] = True
            self.by_size[size] = keys[order], order + 512, may
        self.starts = np.concatenate([np.repeat([False, True], 256), np.array([s for _, s in pieces], bool)])
        p = np.concatenate([np.full(512, 1e-7), np.exp(logs - np.max(logs, initial=0.0))])
        self.logs = np.log(p / p.sum())

    @classmethod
    def of(cls, path: str) -> Vocabulary:
        """The vocabulary of a sentencepiece model file. Scores that only number the pieces are ranks."""
        import sentencepiece

        m = sentencepiece.SentencePieceProcessor(model_file=path)
        found: dict[tuple[bytes, bool], float] = {}
        for k in range(m.get_piece_size()):
            if m.is_control(k) or m.is_unknown(k) or m.is_byte(k) or m.is_unused(k):
                continue
            p = m.id_to_piece(k)
            starts, body = p.startswith("▁"), p.removeprefix("▁")
            # texts come in lower case, so a piece with one of A-Z fits nowhere
            if body and "▁" not in body and not any("A" <= c <= "Z" for c in body):
                found[body.encode(), starts] = m.get_score(k)
        pieces = sorted(found, key=lambda x: (-found[x], x))
        scores = np.array([found[x] for x in pieces])
        ranks = len(scores) > 1 and (scores == np.round(scores)).all()
        return cls(pieces, -np.log(np.arange(len(pieces)) + 50.0) if ranks else scores)


class Scores:
    """Log scores of arcs, a column for each class: inside a word, and at its end. Arcs that start a word
    share one mass, all others another."""

    def __init__(self, starts: np.ndarray, inside: np.ndarray, final: np.ndarray):
        self.inside, self.final = np.empty_like(inside), np.empty_like(final)
        for m in (starts, ~starts):
            whole = inside[m].sum(axis=0) + final[m].sum(axis=0)
            self.inside[m], self.final[m] = np.log(inside[m] / whole), np.log(final[m] / whole)

    @classmethod
    def first(cls, v: Vocabulary, width: int) -> Scores:
        p = np.repeat(np.exp(v.logs)[:, None] / 2, width, axis=1)
        return cls(v.starts, p, p)


class Lattice:
    """The arcs over a batch of words: word, places of begin and end, piece."""

    def __init__(self, words: list[bytes], v: Vocabulary):
        self.sizes = np.array([len(w) for w in words], np.int64)
        self.width = int(self.sizes.max(initial=0))
        data = np.frombuffer(b"".join(words), np.uint8)
        first = np.concatenate([[0], np.cumsum(self.sizes)[:-1]]) if len(words) else np.zeros(0, np.int64)
        rolling = text.Rolling(data)
        word = np.repeat(np.arange(len(words)), self.sizes)
        place = np.arange(len(data)) - first[word]
        left = self.sizes[word] - place
        mark = np.where(place == 0, _START, _U(0))
        at = np.arange(len(data))
        found = [(at, np.ones(len(data), np.int64), data + np.where(place == 0, 256, 0))]
        for size, (keys, index, may) in v.by_size.items():
            at = at[left[at] >= size] if size > 1 else at
            key = rolling.of(at, at + size) ^ mark[at]
            some = np.flatnonzero(may[(key >> _U(48)).astype(np.int64)])
            k = np.minimum(np.searchsorted(keys, key[some]), len(keys) - 1)
            ok = keys[k] == key[some]
            found.append((at[some[ok]], np.full(ok.sum(), size), index[k[ok]]))
        at, size, piece = (np.concatenate(x) for x in zip(*found, strict=True))
        # a single byte may be a piece of the file too: kinds of size 1 must not meet in one group
        kind = np.where(piece < 512, 0, size)
        most = int(kind.max(initial=0)) + 1
        order = np.argsort((place[at] + size) * most + kind, kind="stable")
        self.word, self.begin, self.piece, kind = word[at[order]], place[at[order]], piece[order], kind[order]
        self.end = self.begin + size[order]
        self.last = self.end == self.sizes[self.word]
        # runs of arcs that end at one place and of one kind hold each word once
        self.by_end = self._runs(self.end * most + kind)
        self.backward = np.argsort(-self.begin * most + kind, kind="stable")
        self.by_begin = self._runs((self.begin * most + kind)[self.backward])

    @staticmethod
    def _runs(key: np.ndarray) -> list[tuple[int, int]]:
        cut = np.flatnonzero(key[1:] != key[:-1]) + 1 if len(key) else np.zeros(0, np.int64)
        return list(zip([0, *cut.tolist()], [*cut.tolist(), len(key)], strict=True)) if len(key) else []

    def _scored(self, s: Scores) -> np.ndarray:
        return np.where(self.last[:, None], s.final[self.piece], s.inside[self.piece])

    def forward(self, score: np.ndarray) -> np.ndarray:
        """alpha[w, i]: log probability of the first i bytes, over all cuts, for scores of arcs (one, or
        one a class)."""
        alpha = np.full((len(self.sizes), self.width + 1, *score.shape[1:]), -np.inf)
        alpha[:, 0] = 0
        for a, b in self.by_end:
            w, e = self.word[a:b], self.end[a]
            alpha[w, e] = np.logaddexp(alpha[w, e], alpha[w, self.begin[a]] + score[a:b])
        return alpha

    def scores(self, s: Scores) -> np.ndarray:
        """Log probability of each word under each class."""
        score = np.where(self.last[:, None], s.final[self.piece], s.inside[self.piece])
        return self.forward(score)[np.arange(len(self.sizes)), self.sizes]

    def expected(self, s: Scores, own: np.ndarray, weight: np.ndarray) -> np.ndarray:
        """Expected counts over all cuts, piece x (inside, end of word) x class, each word under its ``own``
        class and counted by ``weight``."""
        c = own[self.word]
        score = np.where(self.last, s.final[self.piece, c], s.inside[self.piece, c])
        alpha = self.forward(score)
        n = np.arange(len(self.sizes))
        whole = alpha[n, self.sizes]
        beta = np.full_like(alpha, -np.inf)
        beta[n, self.sizes] = 0
        for a, b in self.by_begin:
            x = self.backward[a:b]
            w, i = self.word[x], self.begin[x[0]]
            score[x] += beta[w, self.end[x]]
            beta[w, i] = np.logaddexp(beta[w, i], score[x])
        used = np.exp(score + alpha[self.word, self.begin] - whole[self.word]) * weight[self.word]
        size, width = s.inside.shape
        return np.bincount((self.piece * 2 + self.last) * width + c, weights=used, minlength=size * 2 * width).reshape(size, 2, width)


def _batches(words: list[bytes], cells: int = 80_000) -> Iterator[np.ndarray]:
    """Runs of words of like length whose tables stay small."""
    order = np.argsort([len(w) for w in words], kind="stable")
    begin = 0
    while begin < len(order):
        end = begin + 1
        widest = len(words[order[begin]])
        while end < len(order):
            n = len(words[order[end]])
            if n * (end - begin + 1) > cells or n > widest + 4:
                break
            end += 1
        yield order[begin:end]
        begin = end


def _counted(part: pa.RecordBatch) -> tuple[text.Words, np.ndarray, np.ndarray, np.ndarray, np.ndarray]:
    """The words of a slice and their distinct (row, word) pairs: row, word number, count, first place."""
    w = text.words(*common.raw(part.column("text")), text.SPACED)
    u, first, inverse = np.unique(w.hashes, return_index=True, return_inverse=True)
    pairs, n = np.unique(w.rows * max(1, len(u)) + inverse, return_counts=True)
    return w, pairs // max(1, len(u)), pairs % max(1, len(u)), n, first


def word_counts(docs: DataFrame, classes: list) -> DataFrame:
    """h, word and the learning counts per class of all words of all documents. Classes that are not
    named count with the last one."""
    number = {c: k for k, c in enumerate(classes)}
    width = len(classes) + 1

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in batches:
            for part in common.slices(batch, "text", 2 * common.SLICE_BYTES):
                w, row, word, n, first = _counted(part)
                own = np.array([-1 if held else number.get(c, width - 1) for c, held in zip(part.column("class").to_pylist(), part.column("held_out").to_pylist(), strict=True)], np.int64)
                size = len(first)
                k = own[row]
                counts = np.bincount(word[k >= 0] * width + k[k >= 0], weights=n[k >= 0], minlength=size * width).astype(np.int64).reshape(size, width)
                data = w.data.tobytes()
                names = [data[a:b].decode("utf-8", "replace") for a, b in zip(w.begin[first].tolist(), w.end[first].tolist(), strict=True)]
                ends = np.bincount(own[own >= 0], minlength=width)
                yield pa.RecordBatch.from_arrays([
                    pa.array(np.append(w.hashes[first].view(np.int64), np.array([text.hash_of(END)], _U).view(np.int64))), pa.array([*names, END], pa.string()),
                    *(pa.array(np.append(counts[:, c], ends[c])) for c in range(width)),
                ], names=["h", "word", *(f"c{c}" for c in range(width))])

    schema = "h long, word string, " + ", ".join(f"c{c} long" for c in range(width))
    return docs.select("class", "held_out", "text").mapInArrow(run, schema).groupBy("h").agg(F.first("word").alias("word"), *(F.sum(f"c{c}").alias(f"c{c}") for c in range(width)))


def _columns(batch: pa.RecordBatch, width: int) -> np.ndarray:
    return np.stack([batch.column(f"c{k}").to_numpy(zero_copy_only=False) for k in range(width)], axis=1).astype(float)


def adapted(known: DataFrame, v: Vocabulary, width: int, rounds: int = ROUNDS) -> Scores:
    """Arc scores after rounds of expected counts over the distinct learning words (word, c0, c1, ...)."""
    scores = Scores.first(v, width)
    size = len(v.logs)
    for k in range(rounds):
        def run(batches: Iterator[pa.RecordBatch], scores: Scores = scores) -> Iterator[pa.RecordBatch]:
            total = np.zeros((size, 2, width))
            for batch in batches:
                words = [x.encode() for x in batch.column("word").to_pylist()]
                weight = _columns(batch, width)
                row, c = np.nonzero(weight)  # few words are of more than one class
                words, weight = [words[i] for i in row], weight[row, c]
                for own in _batches(words):
                    total += Lattice([words[i] for i in own], v).expected(scores, c[own], weight[own])
            at = np.flatnonzero(total)
            yield pa.RecordBatch.from_arrays([pa.array(at), pa.array(total.ravel()[at])], names=["at", "n"])

        # as many rows as pieces, ends and classes, whatever the corpus
        sums = known.mapInArrow(run, "at long, n double").groupBy("at").agg(F.sum("n").alias("n")).toPandas()
        n = np.zeros(size * 2 * width)
        n[sums["at"].to_numpy(np.int64)] = sums["n"].to_numpy(float)
        n = n.reshape(size, 2, width)
        every = n.sum(axis=2) + FIRST * np.exp(v.logs)[:, None] / 2
        n = n + HELD * (every / every.sum())[:, :, None]
        scores = Scores(v.starts, n[:, 0], n[:, 1])
    return scores


def scored(docs: DataFrame, vocabulary: Vocabulary, hot: int = HOT) -> DataFrame:
    """doc_id, held_out, n_tokens, n_known, train_tokens, base_score, score, piece_score of (doc_id, text,
    class, held_out) rows; those not held out teach."""
    sizes_of = docs.filter("not held_out").groupBy("class").agg(F.count("*").alias("n"))
    known = sizes_of.orderBy(F.desc("n"), "class").limit(CLASSES - 1).collect()
    classes = [r["class"] for r in known]
    width = len(classes) + 1
    counts = common.written(word_counts(docs, classes))
    total = sum((F.col(f"c{c}") for c in range(1, width)), F.col("c0"))
    end_of = F.col("word") == END
    t = counts.agg(
        F.sum(total).alias("n"), F.sum((total > 0).cast("long")).alias("v"),
        *(f(x).alias(f"{name}{c}") for c in range(width) for name, f, x in (("n", F.sum, F.col(f"c{c}")), ("v", F.sum, (F.col(f"c{c}") > 0).cast("long")), ("e", F.sum, F.when(end_of, F.col(f"c{c}")).otherwise(0)))),
    ).first()
    tokens, types = t["n"] or 0, t["v"] or 0
    n, kinds, ends = (np.array([t[f"{k}{c}"] or 0 for c in range(width)], float) for k in "nve")
    width = max(1, width - (not n[-1] and width > 1))  # nothing beyond the named classes
    n, kinds, ends = n[:width], np.maximum(kinds[:width], 1), ends[:width]
    scores = adapted(counts.filter((total > 0) & ~end_of), vocabulary, width)
    stop = np.log((ends + 0.5) / (n + 1))  # of a text that goes on or ends after each word
    go = np.log1p(-np.exp(stop))
    prior = np.log((ends + 1e-3) / (ends + 1e-3).sum())

    def weigh(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in batches:
            words = batch.column("word").to_pylist()
            body = [x.encode() for x in words]
            pieces = np.zeros((len(words), width))
            for own in _batches(body):
                pieces[own] = Lattice([body[k] for k in own], vocabulary).scores(scores) + go
            pieces[[k for k, x in enumerate(words) if x == END]] = stop
            c = _columns(batch, width)
            every = sum(batch.column(f"c{k}").to_numpy(zero_copy_only=False) for k in range(len(classes) + 1))
            with np.errstate(divide="ignore"):
                whole = np.logaddexp(np.log(c), np.log(kinds) + pieces) - np.log(n + kinds)
            base = np.log10((every + 1) / (tokens + types + 1))
            yield pa.RecordBatch.from_arrays([
                batch.column("h"), pa.array(every > 0), pa.array(every.astype(np.int64)), pa.array(base), *(pa.array(x[:, k]) for x in (whole, pieces) for k in range(width)),
            ], names=["h", "known", "n", "base", *names])

    names = [f"{kind}{c}" for kind in "sp" for c in range(width)]
    doubles = ", ".join(f"{x} double" for x in names)
    weighed = common.written(counts.mapInArrow(weigh, f"h long, known boolean, n long, base double, {doubles}"))
    top = _hot(weighed, hot).toPandas().sort_values("h")
    hot_keys, hot_known, hot_base = top["h"].to_numpy(np.int64), top["known"].to_numpy(bool), top["base"].to_numpy(float)
    hot_logs = top[names].to_numpy(float)
    end_hash = np.array([text.hash_of(END)], _U).view(np.int64)[0]

    def split(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in batches:
            for part in common.slices(batch, "text"):
                w, row, word, n, first = _counted(part)
                rows = len(part)
                h = w.hashes[first].view(np.int64)[word] if len(first) else np.zeros(0, np.int64)
                row, h, n = np.append(row, np.arange(rows)), np.append(h, np.full(rows, end_hash)), np.append(n, np.ones(rows, np.int64))
                at = np.minimum(np.searchsorted(hot_keys, h), max(0, len(hot_keys) - 1))
                is_hot = hot_keys[at] == h if len(hot_keys) else np.zeros(len(h), bool)
                r, k, m = row[is_hot], at[is_hot], n[is_hot]
                sums = [np.bincount(r, weights=m * hot_logs[k, c], minlength=rows).astype(float) for c in range(len(names))]
                cold = np.flatnonzero(~is_hot)
                size = rows + len(cold)
                none = pa.array(np.arange(size) >= rows)  # of the lines of rarer words
                pad = lambda x: pa.array(np.concatenate([x, np.zeros(len(cold), x.dtype)]), mask=np.arange(size) >= rows)
                all_rows = pa.array(np.concatenate([np.arange(rows), row[cold]]))
                yield pa.RecordBatch.from_arrays([
                    part.column("key").take(all_rows), part.column("doc_id").take(all_rows), part.column("held_out").take(all_rows), none,
                    pa.array(np.concatenate([np.zeros(rows, np.int64), h[cold]])), pa.array(np.concatenate([np.zeros(rows, np.int64), n[cold]])),
                    pad(np.diff(w.bounds) + 1), pad(np.bincount(r, weights=m * hot_known[k], minlength=rows).astype(np.int64)), pad(np.bincount(r, weights=m * hot_base[k], minlength=rows).astype(float)), *(pad(s) for s in sums),
                ], names=["key", "doc_id", "held_out", "rare", "h", "m", "n_tokens", "n_known", "base", *names])

    kind = dict(docs.dtypes)["doc_id"]
    keyed = docs.select(F.xxhash64(F.coalesce(F.col("doc_id").cast("string"), F.lit("")), F.coalesce("text", F.lit(""))).alias("key"), "doc_id", "held_out", "text")
    out = keyed.mapInArrow(split, f"key long, doc_id {kind}, held_out boolean, rare boolean, h long, m long, n_tokens long, n_known long, base double, {doubles}")
    # each row of documents has one line of sums and one for each of its rarer words
    lines = out.filter("not rare").drop("h", "m", "rare")
    lines = lines.groupBy("key", "doc_id", "held_out").agg(F.count("*").alias("times"), F.first("n_tokens").alias("n_tokens"), *(F.first(c).alias(c) for c in ("n_known", "base", *names)))
    rare = out.filter("rare").select("key", "h", "m")
    seen = rare.join(weighed.select("h", "known", F.col("base").alias("b"), *names), "h")
    more = seen.groupBy("key").agg(
        F.sum(F.when(F.col("known"), F.col("m")).otherwise(0)).alias("k2"), F.sum(F.col("m") * F.col("b")).alias("b2"), *(F.sum(F.col("m") * F.col(c)).alias(f"t{c}") for c in names))
    both = lines.join(more, "key", "left")
    zero, times = F.lit(0.0), F.col("times")

    def mixture(kind: str):
        logs = F.array(*(F.col(f"{kind}{c}") + F.coalesce(F.col(f"t{kind}{c}") / times, zero) + float(prior[c]) for c in range(width)))
        best = F.array_max(logs)
        return (best + F.log(F.aggregate(logs, zero, lambda s, x: s + F.exp(x - best)))) / float(np.log(10))

    result = both.select(
        "doc_id", "held_out", "n_tokens", (F.col("n_known") + F.coalesce((F.col("k2") / times).cast("long"), F.lit(0))).cast("long").alias("n_known"), F.lit(int(tokens)).cast("long").alias("train_tokens"),
        (F.col("base") + F.coalesce(F.col("b2") / times, zero)).alias("base_score"), mixture("s").alias("score"), mixture("p").alias("piece_score"), F.explode(F.sequence(F.lit(1), times.cast("int"))).alias("copy"),
    )
    return result.drop("copy")


def _hot(weighed: DataFrame, most: int) -> DataFrame:
    """The commonest words, at most ``most``: all those above a count that so many words pass."""
    level = F.floor(8 * F.log2(F.greatest(F.col("n"), F.lit(1)).cast("double"))).cast("int")
    held = sorted(((r["level"], r["c"]) for r in weighed.groupBy(level.alias("level")).agg(F.count("*").alias("c")).collect()), reverse=True)
    least, seen = 1 << 30, 0
    for k, c in held:
        seen += c
        if seen > most:
            break
        least = k
    return weighed.filter(level >= least)
