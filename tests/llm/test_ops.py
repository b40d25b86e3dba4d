"""The training-data operators against brute force, held-out rows and odd inputs."""

from __future__ import annotations

import math
import random
import re
import zlib
from collections import Counter

import numpy as np
import pytest
from pyspark.sql import functions as F

from evigraph.llm import common, decontamination, embedding_join, jaccard_join, language_id, lattice_lm, line_dedup, mixing, quality, queries, style_tree, text, url_rules

DOCS = "doc_id long, text string, lang string, source string, n_chars long"


def _docs(spark, texts):
    return spark.createDataFrame([(k, t, "en", "s", len(t or "")) for k, t in enumerate(texts)], DOCS)


def _odd(spark):
    """Nulls in any column, empty and very long texts, repeated rows, a clashing extra column."""
    rows = [(1, None, None, None, None), (None, "a b c d", "en", "s", 7), (2, "", "en", "s", 0), (3, "word " * 30_000, "en", "s", 1), (4, "same row of text here", "en", "s", 2), (4, "same row of text here", "en", "s", 2)]
    return spark.createDataFrame(rows, DOCS).withColumns({"n": F.lit(1), "key": F.lit("k"), "kept": F.lit(2), "items": F.lit(3), "evidence": F.lit(4), "topic": F.lit(5), "class": F.lit(6)})


def _empty(spark):
    return spark.createDataFrame([], DOCS)


def test_word_kernel():
    import pyarrow as pa

    rows = ["Hello  World,x", None, "", "É\tb c", "end"]
    w = text.words(*common.raw(pa.array(rows)))
    got = [[bytes(w.data[i:j]).decode() for i, j in zip(w.begin[a:b], w.end[a:b], strict=True)] for a, b in zip(w.bounds, w.bounds[1:], strict=False)]
    assert got == [["hello", "world,x"], [], [], ["É", "b c"], ["end"]]
    assert text.hash_of("hello") == int(w.hashes[0])


def test_decontamination_brute_blocks_and_proximity(spark, sf):
    docs, bench = spark.read.parquet(f"{sf}/documents.parquet"), spark.read.parquet(f"{sf}/benchmark.parquet")
    items = [tuple(r) for r in bench.collect()]
    for blocks in (decontamination.BLOCK_BYTES, 2000):
        got = {r["doc_id"]: r for r in decontamination.judged(decontamination.matches(docs, bench, ["doc_id"], block_bytes=blocks)).collect()}
        for r in docs.collect():
            for k, v in decontamination.brute(r["text"], items).items():
                assert got[r["doc_id"]][k] == v
    near = spark.createDataFrame([(1, "one two x three four"), (2, "four three two one"), (3, "one a b c d two three four")], "doc_id long, text string")
    q = spark.createDataFrame([(1, "one two three four")], "item_id long, text string")
    hit = {r["doc_id"] for r in decontamination.matches(near, q, ["doc_id"], slop=1).filter(F.size("items") > 0).collect()}
    assert hit == {1}


def test_jaccard_brute(spark, sf):
    docs = [tuple(r) for r in spark.read.parquet(f"{sf}/documents.parquet").select("doc_id", "text").collect()]
    rng = random.Random(3)
    base = [" ".join(rng.choice("alpha beta gamma delta eps zeta eta theta iota kappa lam mu nu".split()) + str(rng.randint(0, 30)) for _ in range(rng.randint(9, 120))).split() for _ in range(12)]
    n = 10_000
    for b in base:
        for _ in range(12):
            w = list(b)
            for _ in range(rng.choice([0, 0, 1, 1, 2, 3])):
                w[rng.randrange(len(w))] = f"edit{rng.randint(0, 5)}"
            docs.append((n, " ".join(w)))
            n += 1
    want = jaccard_join.brute(docs)
    got = {r["doc_id"]: (r["n_shingles"], r["component_id"]) for r in jaccard_join.join(spark.createDataFrame(docs, "doc_id long, text string")).collect()}
    assert got == want and len({v[1] for v in want.values()}) < len(docs) - 40


def test_one_of_each_catches_copies_between_the_limits(spark):
    docs = [(1, None), (2, ""), (3, "one two three"), (4, "One two three")]
    rng = random.Random(11)
    for g in range(6):
        base = [f"{rng.choice('abcdefgh')}{rng.randint(0, 999)}" for _ in range(200)]
        docs.append((10_000 + 10 * g, " ".join(base)))
        for k in range(1, 5):  # 3-word similarity 0.886 and 5-word 0.815 at four edits
            w = list(base)
            for e in range(k + 1):
                w[20 + 40 * e - 5 * k] = f"edit{g}x{k}x{e}"
            docs.append((10_000 + 10 * g + k, " ".join(w)))
    want = {d for d, (_, c) in jaccard_join.brute(docs, 5, 80, 100).items() if c == d}
    got = {r["doc_id"] for r in jaccard_join.one_of_each(spark.createDataFrame(docs, "doc_id long, text string")).collect()}
    assert got == want and len(want) == 9


def test_line_dedup_brute_and_distance(spark):
    rng = random.Random(1)

    def edited(s, n):
        b = list(s)
        for _ in range(n):
            i, r = rng.randint(0, len(b)), rng.random()
            if r < 0.4 and i < len(b):
                b[i] = rng.choice("abcé")
            elif r < 0.7:
                b.insert(i, rng.choice("abcé"))
            elif i < len(b):
                del b[i]
        return "".join(b)

    for _ in range(3000):
        a = "".join(rng.choice("abé") for _ in range(rng.randint(0, 12)))
        b = edited(a, rng.randint(0, 4))
        for t in (1, 2, 3):
            assert line_dedup.within(a.encode(), b.encode(), t) == (line_dedup.distance(a, b) <= t)
    base = ["".join(rng.choice("abcdeé ") for _ in range(rng.randint(22, 40))) for _ in range(40)]
    docs = [(d, None if d == 7 else "\n".join(rng.choice(["", "  "]) + edited(rng.choice(base), rng.choice([0, 0, 1, 2, 3])) for _ in range(rng.randint(0, 6)))) for d in range(60)]
    got = {r["doc_id"]: (r["n_lines"], r["n_exact"], r["n_near"]) for r in line_dedup.deduplicated(spark.createDataFrame(docs, "doc_id long, text string")).collect()}
    assert got == line_dedup.brute(docs)


def test_embedding_join_brute(spark):
    rng = np.random.default_rng(5)
    rows = []
    for k in range(300):
        v = rng.normal(size=8) if k % 3 == 0 or not rows else np.array(rows[rng.integers(len(rows))][1]) + rng.normal(size=8) * rng.choice([0, 0.02, 0.1])
        rows.append((k, [float(np.float32(x)) for x in v], int(k % 2)))
    rows += [(900, None, 1), (901, [0.0] * 8, 1), (902, [float("nan")] * 8, 1), (903, rows[0][1], None), (904, [1.0, 2.0], 1), (905, [2.0, 4.0], 1)]
    df = spark.createDataFrame(rows, "vec_id long, embedding array<float>, label int")
    got = {r["vec_id"]: (r["n_links"], r["component_id"], r["kept"]) for r in embedding_join.join(df).collect()}
    want = embedding_join.brute([r for r in rows if r[0] not in (904, 905)])
    assert {k: v for k, v in got.items() if k < 904} == want and got[904] == (1, 904, True) and got[905] == (1, 904, False)


def test_style_tree_keeps_article_and_drops_the_rest(spark):
    def page(k):
        return (
            f"<html><head><title>t{k}</title></head><body><div class='top'>Same site banner</div><nav>menu</nav><div class=\"ad\">buy {k}</div><article><h1>Head {k} &amp; more</h1><p>Body   text {k}<br>goes\non<p>Second <b>para {k}"
            f"</article><div id=comments>reader {k}</div><form>f</form><script>if (a < b) x = '</p>';</script><footer>&copy; x</footer></body></html>"
        )

    rows = [(k, f"http://h.example.org/{k}", page(k)) for k in range(20)] + [(100, None, None), (101, "x", "")]
    got = {r["page_id"]: r for r in style_tree.extracted(spark.createDataFrame(rows, "page_id long, url string, html string")).collect()}
    assert got[3]["text"] == "Head 3 & more\nBody text 3 goes on\nSecond para 3" and got[3]["n_chars"] == len(got[3]["text"])
    assert got[100]["text"] == "" and got[101]["text"] == ""
    few = style_tree.extracted(spark.createDataFrame(rows, "page_id long, url string, html string"), sent=0)
    assert {r["page_id"]: r["text"] for r in few.collect()} == {k: r["text"] for k, r in got.items()}


def test_style_tree_copies_do_not_cut_the_article(spark):
    def page(words, n):
        return f"<html><body><div class='top'>Same site banner</div><div class='wrap'><article><h1>Head {words}</h1><p>Story {words}</article></div><!-- {n} --></body></html>"

    rows = [(k, f"http://copied.example.org/{k}", page("one" if k < 15 else f"own {k}", 0)) for k in range(20)]
    rows += [(100 + k, f"http://same.example.org/{k}", page("all", 0)) for k in range(20)]
    rows += [(200 + k, f"http://large.example.org/{k}", page("one" if k < 60 else f"own {k}", 0)) for k in range(80)]
    df = spark.createDataFrame(rows, "page_id long, url string, html string")
    got = {r["page_id"]: r["text"] for r in style_tree.extracted(df).collect()}
    banner = "Same site banner\n"
    text_of = lambda words: f"Head {words}\nStory {words}"
    assert all(got[k] == banner + text_of("one" if k < 15 else f"own {k}") for k in range(20))
    assert all(got[100 + k] == banner + text_of("all") for k in range(20))
    assert all(got[200 + k] == text_of("one" if k < 60 else f"own {k}") for k in range(80))
    low = style_tree.main_text(style_tree.parse(page("one", 0)), lambda c: c.tag in ("html", "body", "div", "article"))
    assert low == text_of("one")


def test_style_tree_alone_removes_what_no_name_tells(spark):
    """Banner, link list, stock adverts and footer lines without a telling tag or class, on a host that the
    tree knows; the same on a host of few pages stays."""
    stock = [f"offer number {k}" for k in range(5)]

    def page(k, body):
        own = f"story {k} " + " ".join(f"w{(k * 7 + i) % 97}x{i}" for i in range(30))
        return f"<html><body><div class='q1'><span>One site, one voice</span></div><div class='q2'><a href=/a>{stock[k % 5]}</a> <a href=/b>more</a></div><{body}><p>{own}</p><p>end {k}</p></{body}><div class='q3'>imprint {stock[(k * 3) % 5]}</div></body></html>", f"{own}\nend {k}"

    rows, want = [], {}
    for k in range(60):
        body = "article" if k % 2 else "div"  # unnamed content too
        html, want[k] = page(k, body)
        rows.append((k, f"http://{'known' if k < 50 else f'few{k}'}.example.org/{k}", html))
    df = spark.createDataFrame(rows, "page_id long, url string, html string")
    for names in (False, True):
        got = {r["page_id"]: r["text"] for r in style_tree.extracted(df, names=names).collect()}
        assert all(got[k] == want[k] for k in range(50))
        assert all(want[k] in got[k] and "One site, one voice" in got[k] for k in range(50, 60))
    blocks = {r["page_id"]: r["text"] for r in style_tree.extracted(df, sent=0).collect()}
    assert blocks == got


def test_style_tree_leaves_unique_texts_of_a_stocked_branch(spark):
    """Of an unnamed branch that often holds the same text, pages that hold their own keep it."""
    rows = [(k, f"http://h.example.org/{k}", f"<body><div class=z><p>{'nothing here yet' if k < 24 else f'own words {k} {k * k}'}</p></div><article><p>art {k}</article>") for k in range(60)]
    got = {r["page_id"]: r["text"] for r in style_tree.extracted(spark.createDataFrame(rows, "page_id long, url string, html string")).collect()}
    assert all(got[k] == (f"art {k}" if k < 24 else f"own words {k} {k * k}\nart {k}") for k in range(60))


def test_style_tree_deep_long_and_repeated_pages(spark):
    deep = "<div>" * 20_000 + "deep" + "</b>" * 20_000
    rows = [(1, "http://a.b/1", deep), (2, "http://a.b/2", "<p>" + "long text " * 100_000), (3, "http://a.b/3", "<p>same"), (3, "http://a.b/3", "<p>same"), (None, None, None), (4, "http://a.b/4", "")]
    df = spark.createDataFrame(rows, "page_id long, url string, html string").withColumns({"text": F.lit("clash"), "n_chars": F.lit(1), "key": F.lit(2)})
    got = sorted(((r["page_id"] or 0), r["text"], r["n_chars"]) for r in style_tree.extracted(df).collect())
    assert got == [(0, "", 0), (1, "deep", 4), (2, ("long text " * 100_000).strip(), 999_999), (3, "same", 4), (3, "same", 4), (4, "", 0)]


def test_url_rules(spark):
    rows = [(1, "http://a.example.net/en/1"), (2, "http://b.net/x"), (3, "https://Example.com/de/2?q"), (4, "http://x.org/fr/"), (5, None), (6, "nohost"), (7, "http://notexample.com/de/"), (8, "http://example.net?en/")]
    labels = spark.createDataFrame([], "page_id long, label string")
    got = {r["page_id"]: (r["host"], r["path"], r["rule"], r["verdict"]) for r in url_rules.judged(spark.createDataFrame(rows, "page_id long, url string"), labels).collect()}
    assert got == {
        1: ("a.example.net", "/en/1", "example.net/en/", "allow"), 2: ("b.net", "/x", "net/", "block"), 3: ("example.com", "/de/2", "example.com/de/", "block"), 4: ("x.org", "/fr/", "org/fr/", "allow"),
        5: ("", "", None, "allow"), 6: ("", "", None, "allow"), 7: ("notexample.com", "/de/", None, "allow"), 8: ("example.net", "", None, "allow"),
    }
    pages = [(k, f"http://{'spam' if k % 4 == 0 else 'fine'}.example.org/a/{k}") for k in range(200)]
    lab = spark.createDataFrame([(k, "block" if k % 4 == 0 else "allow") for k in range(100)], "page_id long, label string")
    got = {r["page_id"]: r["verdict"] for r in url_rules.judged(spark.createDataFrame(pages, "page_id long, url string"), lab, support=0.05).collect()}
    assert sum(got[k] == ("block" if k % 4 == 0 else "allow") for k in range(200)) >= 190


def test_url_rules_of_the_majority_of_queries_and_of_narrow_sections(spark):
    rows, lab = [], []

    def add(n, url, block):
        for k in range(n):
            rows.append((len(rows), url.format(k)))
            lab.append((len(lab), "block" if k < block * n else "allow"))

    add(400, "http://clean.example.org/x/{}", 0)
    add(100, "http://shop.example.com/offers/{}", 0.9)
    add(40, "http://shop.example.com/manual/{}", 0.05)  # the host is blocked at 0.66, this section is clean
    add(40, "http://wiki.example.com/p/{}?print=1&sessionid=7", 1)
    add(60, "http://wiki.example.com/p/{}?page=2", 0)
    pages, labels = spark.createDataFrame(rows, "page_id long, url string"), spark.createDataFrame(lab, "page_id long, label string")
    allowed = sum(v == "allow" for _, v in lab) / len(lab)
    assert allowed > 2 / 3
    cut = pages.withColumns(url_rules.parts())
    made = url_rules.mined(cut.select("page_id", url_rules.tokens(F.col("host"), F.col("path"), F.col("query")).alias("tokens")).join(labels, "page_id").select("tokens", "label")).collect()
    assert {r["verdict"] for r in made} == {"allow", "block"} and any("query:sessionid" in r["tokens"] for r in made)
    new = [(1, "http://shop.example.com/offers/new"), (2, "http://shop.example.com/manual/new"), (3, "http://wiki.example.com/p/new?print=1&SessionID=8"), (4, "http://wiki.example.com/p/new?page=9"), (5, "http://wiki.example.com/p/new")]
    both = pages.select((F.col("page_id") + 100).alias("page_id"), "url").unionByName(spark.createDataFrame(new, "page_id long, url string"))
    moved = labels.withColumn("page_id", F.col("page_id") + 100)
    for sent in (url_rules.SENT, 0):
        got = {r["page_id"]: r["verdict"] for r in url_rules.judged(both, moved, given=(url_rules.Given("nowhere.test", "/", "block"),), sent=sent).filter("page_id < 100").collect()}
        assert got == {1: "block", 2: "allow", 3: "block", 4: "allow", 5: "allow"}


def test_url_rules_of_long_paths_and_the_two_ways_agree(spark):
    """Many words that come together, and many that come in any company: neither way doubles with each."""
    rng = random.Random(2)
    words = [f"p{k}" for k in range(30)]
    rows = [(k, f"http://a.example.org/{'/'.join(words)}/{k}" if k % 2 else f"http://b.example.org/{'/'.join(w for w in words[:18] if rng.random() < 0.8)}") for k in range(120)]
    lab = spark.createDataFrame([(k, "block" if k % 2 else "allow") for k in range(120)], "page_id long, label string")
    pages = spark.createDataFrame(rows, "page_id long, url string")
    got = {r["page_id"]: r["verdict"] for r in url_rules.judged(pages, lab, given=(url_rules.Given("nowhere.test", "/", "block"),)).collect()}
    assert all(got[k] == ("block" if k % 2 else "allow") for k in range(120))
    few = [(k, ["host:x", *(f"t{i}" for i in range(8) if (k * (i + 3)) % 5 < 3)], "block" if k % 3 else "allow") for k in range(200)]
    df = spark.createDataFrame(few, "page_id long, tokens array<string>, label string").select("tokens", "label")
    show = lambda w: {(tuple(sorted(r["items"])), r["freq"]) for r in url_rules.combinations(df, 20, 200, w)[0].collect()}
    assert show(14) == show(2) and len(show(2)) > 50
    rules = lambda w: {(tuple(r["tokens"]), r["verdict"], round(r["confidence"], 9)) for r in url_rules.mined(df, wide=w).collect()}
    assert rules(14) == rules(2)


def test_url_rules_odd_rows(spark):
    rows = [(1, "http://a.net/" + "x/" * 50_000), (2, None), (2, None), (3, ""), (None, "http://a.org/fr/"), (4, "http://a.net/"), (4, "http://a.net/")]
    pages = spark.createDataFrame(rows, "page_id long, url string").withColumns({"tokens": F.lit("clash"), "host": F.lit("h"), "rule": F.lit(1)})
    labels = spark.createDataFrame([(1, "block"), (2, None), (None, "allow")], "page_id long, label string")
    got = sorted((r["page_id"] or 0, r["host"], r["rule"] or "", r["verdict"]) for r in url_rules.judged(pages, labels).collect())
    assert got == [(0, "a.org", "org/fr/", "allow"), (1, "a.net", "net/", "block"), (2, "", "", "allow"), (2, "", "", "allow"), (3, "", "", "allow"), (4, "a.net", "net/", "block"), (4, "a.net", "net/", "block")]


def test_stored_index_of_positions(spark, sf):
    docs = spark.read.parquet(f"{sf}/documents.parquet").select("doc_id", "text")
    index = decontamination.stored(docs)
    texts = {r["doc_id"]: re.findall(r"[^\x00-\x2F\x3A-\x60\x7B-\x7F]+", re.sub("[A-Z]", lambda m: m[0].lower(), r["text"] or "")) for r in docs.collect()}
    rng = random.Random(6)
    long = [d for d, w in texts.items() if len(w) > 30]
    for _ in range(4):
        d = rng.choice(long)
        k = rng.randrange(len(texts[d]) - 4)
        phrase = texts[d][k : k + rng.randint(1, 4)]
        want = {(e, i) for e, w in texts.items() for i in range(len(w) - len(phrase) + 1) if w[i : i + len(phrase)] == phrase}
        assert {(r["doc"], r["at"]) for r in decontamination.searched(index, " ".join(phrase)).collect()} == want
    assert decontamination.searched(index, "").count() == 0 and decontamination.searched(index, "nosuchword here").count() == 0
    near = spark.createDataFrame([(1, "one two x three four"), (2, "four three two one"), (3, "one a b c d two three four")], "doc_id long, text string")
    assert {r["doc"] for r in decontamination.searched(decontamination.stored(near), "one two three four", slop=1).collect()} == {1}


def test_language_on_held_out(spark, sf):
    r = queries.op6_rank_order_language(spark, sf).join(spark.read.parquet(f"{sf}/documents.parquet").select("doc_id", "lang"), "doc_id")
    n = r.filter("held_out and lang is not null")
    assert n.filter("lang = lang_pred").count() >= 0.95 * n.count() and r.filter("score < 0 or score > 1").count() == 0
    odd = language_id.predicted(_odd(spark).select("doc_id", "text"), {}).collect()
    assert {x["lang_pred"] for x in odd} == {"und"}


def test_lattice_counts_and_probability(spark, sf):
    rows = [tuple(r) for r in spark.read.parquet(f"{sf}/documents.parquet").select("doc_id", "text").collect()]
    low = lambda s: re.sub("[A-Z]", lambda m: m[0].lower(), s or "")
    toks = {i: [*re.findall(r"[^\x20\x09-\x0D]+", low(t)), "\n"] for i, t in rows}
    c = Counter()
    for i, w in toks.items():
        if zlib.crc32(str(i).encode()) % 7 != 2:
            c.update(w)
    n, v = sum(c.values()), len(c)
    for r in queries.op1_subword_lattice(spark, sf).collect():
        w = toks[r["doc_id"]]
        assert (r["n_tokens"], r["n_known"], r["train_tokens"]) == (len(w), sum(c[x] > 0 for x in w), n)
        assert r["base_score"] == pytest.approx(sum(math.log10((c[x] + 1) / (n + v + 1)) for x in w), rel=1e-9) and r["score"] < 0


def _cuts(word, v):
    """All cuts of a word: lists of (piece, whether it ends the word)."""
    if not word:
        yield []
        return

    def rest(i):
        if i == len(word):
            yield []
            return
        arcs = [(word[i] + (256 if i == 0 else 0), 1)] + [(512 + k, len(b)) for k, (b, starts) in enumerate(v.pieces) if starts == (i == 0) and word[i : i + len(b)] == b]
        for piece, size in arcs:
            for more in rest(i + size):
                yield [(piece, i + size == len(word)), *more]

    yield from rest(0)


SMALL = [(b"a", True), (b"ab", True), (b"b", False), (b"ba", False), (b"a", False), (b"cab", True)]


def test_lattice_forward_is_the_sum_over_cuts():
    v = lattice_lm.Vocabulary(SMALL, -np.log(np.arange(6) + 2.0))
    rng = np.random.default_rng(3)
    p = rng.random((2, len(v.logs), 3))
    s = lattice_lm.Scores(v.starts, p[0], p[1])
    words = [b"ab", b"aba", b"b", b"abab", b"c", "é".encode(), b"cabba"]
    lat = lattice_lm.Lattice(words, v)
    of = lambda cut: np.exp(sum((s.final if last else s.inside)[piece] for piece, last in cut))
    want = np.array([sum(of(c) for c in _cuts(w, v)) for w in words])
    assert np.allclose(np.exp(lat.scores(s)), want, rtol=1e-9)
    weight, own = rng.random(len(words)), rng.integers(0, 3, len(words))
    counts = np.zeros((len(v.logs), 2, 3))
    for w, m, k, whole in zip(words, weight, own, want, strict=True):
        for c in _cuts(w, v):
            for piece, last in c:
                counts[piece, int(last), k] += m * of(c)[k] / whole[k]
    assert np.allclose(lat.expected(s, own, weight), counts)


def test_lattice_word_probabilities_sum_to_one():
    """Every word of up to six letters of a one-letter alphabet, and the rest by its geometric tail."""
    v = lattice_lm.Vocabulary([(b"a", True), (b"aa", False)], np.zeros(2))
    p = np.zeros((len(v.logs), 1))
    p[[ord("a"), ord("a") + 256, 512, 513]] = [[0.2], [0.3], [0.5], [0.1]]
    s = lattice_lm.Scores(v.starts, p + 1e-300, 3 * p + 1e-300)
    words = [b"a" * k for k in range(1, 60)]
    assert np.exp(lattice_lm.Lattice(words, v).scores(s)).sum() == pytest.approx(1.0, abs=1e-9)


def test_lattice_scores_against_brute(spark):
    texts = ["ab aba Ab b", "ab cab ba\tab", "b b aba", None, "", "cab cab ab zz", "abab b", "ba ab é", "same text", "same text"]
    rows = [(k if k < 8 else 8, t, "xy"[k % 2] if k != 4 else None, k % 4 == 3) for k, t in enumerate(texts)]
    v = lattice_lm.Vocabulary(SMALL, -np.log(np.arange(6) + 2.0))
    df = spark.createDataFrame(rows, "doc_id long, text string, class string, held_out boolean")
    split = lambda t: re.findall(r"[^\x20\x09-\x0D]+", re.sub("[A-Z]", lambda m: m[0].lower(), t or ""))
    learn = [r for r in rows if not r[3]]
    classes = sorted({r[2] for r in learn}, key=lambda c: (-sum(r[2] == c for r in learn), c is not None, c or ""))
    counts = [Counter(w for r in learn if r[2] == c for w in split(r[1])) for c in classes]
    ends = [sum(r[2] == c for r in learn) for c in classes]
    width = len(classes)
    first = np.repeat(np.exp(v.logs)[:, None] / 2, width, axis=1)
    s = lattice_lm.Scores(v.starts, first, first)
    of = lambda cut, k: math.exp(sum((s.final if last else s.inside)[piece, k] for piece, last in cut))
    prob = lambda w, k: sum(of(c, k) for c in _cuts(w.encode(), v))
    for _ in range(lattice_lm.ROUNDS):
        n = np.zeros((len(v.logs), 2, width))
        for k in range(width):
            for w, m in counts[k].items():
                for c in _cuts(w.encode(), v):
                    for piece, last in c:
                        n[piece, int(last), k] += m * of(c, k) / prob(w, k)
        every = n.sum(axis=2) + lattice_lm.FIRST * np.exp(v.logs)[:, None] / 2
        n = n + lattice_lm.HELD * (every / every.sum())[:, :, None]
        s = lattice_lm.Scores(v.starts, n[:, 0], n[:, 1])
    size = [sum(c.values()) + e for c, e in zip(counts, ends, strict=True)]
    kinds = [len(c) + (e > 0) for c, e in zip(counts, ends, strict=True)]
    stop = [(e + 0.5) / (n + 1) for e, n in zip(ends, size, strict=True)]

    def text_score(words, arcs):
        out = []
        for k in range(width):
            z = math.log((ends[k] + 1e-3) / sum(e + 1e-3 for e in ends))
            for w in [*words, None]:
                p = (1 - stop[k]) * prob(w, k) if w is not None else stop[k]
                c = counts[k][w] if w is not None else ends[k]
                z += math.log((c + kinds[k] * p) / (size[k] + kinds[k]) if arcs else p)
            out.append(z)
        return (max(out) + math.log(sum(math.exp(z - max(out)) for z in out))) / math.log(10)

    for hot in (lattice_lm.HOT, 2, 0):
        got = sorted((r["doc_id"], r["score"], r["piece_score"]) for r in lattice_lm.scored(df, v, hot=hot).collect())
        want = sorted((r[0], text_score(split(r[1]), True), text_score(split(r[1]), False)) for r in rows)
        assert len(got) == len(want)
        for g, w in zip(got, want, strict=True):
            assert g == pytest.approx(w, rel=1e-9)


def test_lattice_beats_the_base_on_held_out(spark):
    r = queries.op1_subword_lattice(spark, "/root/testdata/sf0.1").filter("held_out").agg(F.sum("score"), F.sum("base_score"), F.sum("piece_score")).first()
    assert r[0] > r[1] and r[0] > r[2]


def test_raking_meets_both_margins():
    tokens, rows, cols = np.array([10.0, 20, 30, 40]), np.array([0, 0, 1, 1]), np.array([0, 1, 0, 1])
    w = mixing.rake(tokens, [rows, cols], [np.array([0.5, 0.5]), np.array([0.7, 0.3])])
    got = tokens * w / 100
    assert np.allclose(np.bincount(rows, got), [0.5, 0.5]) and np.allclose(np.bincount(cols, got), [0.7, 0.3])
    c = mixing._scale(tokens, w, 40.0)
    assert (tokens * np.minimum(1, c * w)).sum() == pytest.approx(40.0)


def test_mixing_table_way_agrees(spark, sf):
    docs = spark.read.parquet(f"{sf}/documents.parquet")
    a = {r["doc_id"]: r["probability"] for r in mixing.mixed(docs, sweeps=8).collect()}
    b = {r["doc_id"]: r["probability"] for r in mixing.mixed(docs, cells_limit=3, sweeps=8).collect()}
    assert a.keys() == b.keys() and max(abs(a[k] - b[k]) for k in a) < 1e-6


def test_mixing_ways_meet_the_same_gap(spark):
    # sources and languages go together, so the fit needs more than ten sweeps
    cells = [(f"s{i}" if i else None, f"l{j}", t, (1000 * (i + 1) if i == j else 300 + 7 * i) * (t + 1)) for i in range(3) for j in range(3) for t in range(2)]
    profile = spark.createDataFrame(cells, "source string, lang string, topic int, n_tokens long")
    run = lambda **o: {(r["source"], r["lang"], r["topic"]): (r["weight"], r["probability"]) for r in mixing.calibrated(profile, **o).collect()}
    given = {"source": {None: 0.5, "s1": 0.2}, "lang": {"l2": 0.1}}
    tokens = {c[:3]: c[3] for c in cells}
    total = sum(tokens.values())
    for targets in (None, given):
        a, b = run(targets=targets), run(targets=targets, cells_limit=3)
        assert a.keys() == b.keys() and max(abs(a[k][1] - b[k][1]) for k in a) < 1e-6
    share = lambda place, name: sum(tokens[k] * a[k][0] for k in a if k[place] == name) / total
    assert share(0, None) == pytest.approx(0.5) and share(0, "s1") == pytest.approx(0.2) and share(0, "s2") == pytest.approx(0.3) and share(1, "l2") == pytest.approx(0.1)
    before = {j: sum(v for k, v in tokens.items() if k[1] == j) for j in ("l0", "l1")}
    assert share(1, "l0") / share(1, "l1") == pytest.approx(before["l0"] / before["l1"])
    assert sum(tokens[k] * a[k][1] for k in a) == pytest.approx(0.5 * total)
    with pytest.raises(ValueError):
        run(targets={"lang": {"l0": 0.8, "l1": 0.4}})
    with pytest.warns(RuntimeWarning, match="after 2 sweeps"):
        run(sweeps=2)
    with pytest.warns(RuntimeWarning, match="after 2 sweeps"):
        run(cells_limit=3, sweeps=2)


def test_topics_find_the_words_that_go_together(spark):
    rng = random.Random(4)
    vocabularies = [[f"w{g}x{k}" for k in range(40)] for g in range(3)]
    docs = [(k, " ".join(rng.choice(vocabularies[k % 3]) for _ in range(60)) + " and the of") for k in range(240)] + [(900, None), (901, "")]
    df = spark.createDataFrame(docs, "doc_id long, text string")
    model = mixing.topics(df, 3)
    got = {r["doc_id"]: r["topic"] for r in mixing.profiled(df, model).collect()}
    assert got[900] == got[901] == -1
    assert all(len({got[k] for k in range(240) if k % 3 == g}) == 1 for g in range(3)) and len({got[g] for g in range(3)}) == 3
    again = {r["doc_id"]: r["topic"] for r in mixing.profiled(df, mixing.topics(df.repartition(3), 3)).collect()}
    assert again == got


def test_quality_on_held_out(spark):
    sf = "/root/testdata/sf0.01"
    docs, labels = spark.read.parquet(f"{sf}/documents.parquet"), spark.read.parquet(f"{sf}/labels.parquet")
    r = quality.judged(docs, labels.filter("doc_id % 3 <> 0")).join(labels.filter("doc_id % 3 = 0"), "doc_id")
    good = r.filter("quality = 1 and toxic = 0")
    assert good.filter("keep").count() >= 0.9 * good.count()
    junk = r.filter("quality = 0")
    assert junk.filter("not keep").count() >= 0.5 * junk.count()


def test_quality_fits_all_labelled(spark):
    docs = spark.range(24_000).select(F.col("id").alias("doc_id"), F.when(F.col("id") % 2 == 0, "alpha").otherwise("beta").alias("text"), F.lit("s").alias("source"), F.lit("l").alias("lang"))
    # in the lower third of the hashes alpha is the bad word, in the other two thirds beta
    low = F.xxhash64("doc_id", "text") < int(-(1 << 63) + (1 << 64) / 3)
    labels = docs.select("doc_id", ((F.col("text") == "alpha") != low).cast("int").alias("quality"), F.lit(0).alias("toxic"))
    first = quality.judged(docs, labels, keep_text=True)
    assert sorted(tuple(r) for r in first.select("text", "keep").distinct().collect()) == [("alpha", True), ("beta", False)]
    share = labels.join(docs, "doc_id").filter("text = 'beta'").agg(F.avg(1 - F.col("quality"))).first()[0]
    p = first.filter("text = 'beta'").first()["evidence"]
    assert abs(1 / (1 + np.exp(-p)) - share) < 0.02  # the classes are of one size, so evidence is the log odds
    again = quality.judged(docs.repartition(7), labels, keep_text=True)
    assert {tuple(r) for r in first.select("text", "evidence").distinct().collect()} == {tuple(r) for r in again.select("text", "evidence").distinct().collect()}


@pytest.mark.parametrize("make", [_odd, _empty])
def test_odd_inputs(spark, make):
    docs = make(spark)
    n = docs.count()
    bench = spark.createDataFrame([(1, "same row of text here"), (None, "x"), (2, None)], "item_id long, text string")
    labels = spark.createDataFrame([(3, 0, 0), (4, 1, None), (None, 1, 1)], "doc_id long, quality int, toxic int")
    assert decontamination.judged(decontamination.matches(docs, bench, ["doc_id"])).count() == n
    assert decontamination.decontaminated(docs, bench).count() == max(0, n - 2)
    assert jaccard_join.join(docs).count() == n
    assert jaccard_join.one_of_each(docs).columns == docs.columns
    assert line_dedup.deduplicated(docs).count() == n and line_dedup.without_repeats(docs).columns == docs.columns
    assert quality.judged(docs.select("doc_id", "source", "lang", "text"), labels).count() == n and quality.good(docs, labels).columns == docs.columns
    assert mixing.mixed(docs.select("doc_id", "source", "lang", "text")).count() == n and mixing.sampled(docs).columns == docs.columns
    rows = docs.select("doc_id", "text", F.col("lang").alias("class"), F.lit(False).alias("held_out"))
    assert lattice_lm.scored(rows, lattice_lm.Vocabulary(SMALL, np.zeros(6))).count() == n
    model = language_id.profiles(docs)
    assert language_id.predicted(docs.select("doc_id", "text"), model).count() == n
    v = spark.createDataFrame([], "vec_id long, embedding array<float>, label int")
    assert embedding_join.join(v).count() == 0
    p = spark.createDataFrame([], "page_id long, url string, html string")
    assert style_tree.extracted(p).count() == 0 and url_rules.judged(p, url_rules.labels_of(labels)).count() == 0


def test_pipeline_stages_against_brute(spark, sf, tmp_path):
    import corpus_pipeline as cp

    docs = spark.read.parquet(f"{sf}/documents.parquet")
    names = [n for n, _ in cp.STAGES]
    assert len(names) == 5
    columns = docs.columns
    for k, (_, stage) in enumerate(cp.STAGES):
        stage(spark, docs, sf).write.parquet(str(tmp_path / str(k)))
        out = spark.read.parquet(str(tmp_path / str(k)))
        assert out.columns == columns and 0 < out.count() <= docs.count()
        if k == 1:
            want = line_dedup.brute([tuple(r) for r in docs.select("doc_id", "text").collect()])
            rows = {r["doc_id"]: r["text"] for r in out.collect()}
            for d, t in ((r["doc_id"], r["text"]) for r in docs.collect()):
                if d in rows and t:
                    assert rows[d].count("\n") + 1 == want[d][0] - want[d][1] - want[d][2]
        if k == 2:
            want = jaccard_join.brute([tuple(r) for r in docs.select("doc_id", "text").collect()], 5, 80, 100)
            assert {r["doc_id"] for r in out.collect()} == {d for d, (_, c) in want.items() if c == d}
        if k == 3:
            items = [tuple(r) for r in spark.read.parquet(f"{sf}/benchmark.parquet").collect()]
            assert {r["doc_id"] for r in out.collect()} == {r["doc_id"] for r in docs.collect() if not decontamination.brute(r["text"], items)["contaminated"]}
        docs = out


def test_embedding_ties_repeated_and_null_ids(spark):
    a, b = [1.0, 0.0, 0.0, 0.0], [49.0, 9.0, 3.0, 3.0]  # their cosine is 49 / 50
    rows = [
        (10, a, 1), (11, b, 1), (12, [49.0, 9.0, 3.0, 3.1], 1), (13, [2.0, 0.0, 0.0, 0.0], 1), (20, [1e200, 1e200, 0.0, 0.0], 2), (21, [1.0, 1.0, 0.0, 0.0], 2),
        (22, [1e-200, 1e-200, 0.0, -0.0], 2), (30, a, 3), (30, a, 3), (None, a, 3), (31, None, 3), (32, [], 3), (33, [None, 1.0], 3), (34, [float("inf"), 1.0], 3),
    ]
    df = spark.createDataFrame(rows, "vec_id long, embedding array<double>, label int").withColumns({"n": F.lit(1), "point": F.lit("x"), "n_links": F.lit(2)})
    got = sorted((r["vec_id"] or 0, r["n_links"], r["component_id"] or 0, r["kept"]) for r in embedding_join.join(df).collect())
    assert got == [
        (0, 0, 0, False), (10, 2, 10, True), (11, 3, 10, False), (12, 1, 10, False), (13, 2, 10, False), (20, 2, 20, True), (21, 2, 20, False), (22, 2, 20, False),
        (30, 1, 30, True), (30, 1, 30, True), (31, 0, 31, True), (32, 0, 32, True), (33, 0, 33, True), (34, 0, 34, True),
    ]


def test_embedding_dense_group_over_many_blocks(spark, monkeypatch):
    monkeypatch.setattr(embedding_join, "BLOCK", 16)
    monkeypatch.setattr(embedding_join, "LEAF", 4)
    rng = np.random.default_rng(8)
    center = rng.normal(size=12)
    rows = [(k, (center + rng.normal(size=12) * rng.choice([0.02, 0.15, 0.4])).tolist(), 0) for k in range(160)]
    df = spark.createDataFrame(rows, "vec_id long, embedding array<double>, label int")
    got = {r["vec_id"]: (r["n_links"], r["component_id"], r["kept"]) for r in embedding_join.join(df).collect()}
    assert got == embedding_join.brute(rows)


def test_odd_rows_by_value(spark):
    odd = _odd(spark)
    by = lambda rows: sorted(rows, key=str)
    got = by((r["doc_id"], r["n_shingles"], r["component_id"]) for r in jaccard_join.join(odd).collect())
    assert got == by([(1, 0, 1), (None, 2, None), (2, 0, 2), (3, 1, 3), (4, 3, 4), (4, 3, 4)])
    lines = by((r["doc_id"], r["n_lines"], r["n_exact"], r["n_near"]) for r in line_dedup.deduplicated(odd).collect())
    assert lines == by([(1, 0, 0, 0), (None, 1, 0, 0), (2, 1, 0, 0), (3, 1, 0, 0), (4, 1, 0, 0), (4, 1, 0, 0)])
    four = ("doc_id", "source", "lang", "text")
    none = spark.createDataFrame([], "doc_id long, quality int, toxic int")
    one_class = spark.createDataFrame([(3, 1, 0), (4, 1, 0)], "doc_id long, quality int, toxic int")
    for labels in (none, one_class):
        assert [(r["evidence"], r["keep"]) for r in quality.judged(odd.select(*four), labels).collect()] == [(0.0, True)] * 6
    m = by((r["doc_id"], r["n_tokens"], r["topic"], 0 <= r["probability"] <= 1, r["weight"] > 0) for r in mixing.mixed(odd.select(*four)).collect())
    assert [x[:2] + x[3:] for x in m] == [x for x in by([(1, 0, True, True), (None, 4, True, True), (2, 0, True, True), (3, 30_000, True, True), (4, 5, True, True), (4, 5, True, True)])]
    assert {x[2] for x in m if not x[1]} == {-1}
    model = language_id.profiles(odd.withColumn("lang", F.lit("en")))
    lang = by((r["doc_id"], r["lang_pred"], r["score"]) for r in language_id.predicted(odd.select("doc_id", "text"), model).collect())
    assert lang == by([(1, "und", 0.0), (None, "en", 1.0), (2, "und", 0.0), (3, "en", 1.0), (4, "en", 1.0), (4, "en", 1.0)])
    high = spark.createDataFrame([(1, "\U00030001\U00030002")], "doc_id long, text string")  # letters of a high plane
    assert language_id.predicted(high, language_id.profiles(high.withColumn("lang", F.lit("zh")))).first()["lang_pred"] == "zh"


@pytest.mark.parametrize("make", [_odd, _empty])
def test_whole_pipeline_on_odd_and_empty_tables(spark, make, tmp_path):
    import corpus_pipeline as cp

    make(spark).write.parquet(str(tmp_path / "documents.parquet"))
    spark.createDataFrame([(3, 1, 0)] if make is _odd else [], "doc_id long, quality int, toxic int").write.parquet(str(tmp_path / "labels.parquet"))
    spark.createDataFrame([(1, "same row of text here"), (None, None)] if make is _odd else [], "item_id long, text string").write.parquet(str(tmp_path / "benchmark.parquet"))
    docs, columns = spark.read.parquet(str(tmp_path / "documents.parquet")), make(spark).columns
    for name, stage in cp.STAGES:
        before, docs = docs, common.written(stage(spark, docs, str(tmp_path)))
        assert docs.columns == columns, name
    assert sorted(r["doc_id"] or 0 for r in before.collect()) == ([0, 1, 2, 3] if make is _odd else [])
    assert {r["doc_id"] for r in docs.collect()} <= {None, 1, 2, 3}


def test_topics_are_fitted_on_all_documents(spark):
    import pyarrow as pa

    rng = np.random.default_rng(5)
    texts = [" ".join(f"{'abc'[k % 3]}{rng.integers(40)}" for _ in range(12)) for k in range(6000)] + ["", None]
    docs = spark.createDataFrame([(t,) for t in texts], "text string")
    model = mixing.topics(docs, 3)
    # the same by hand: every document counts
    batch = pa.RecordBatch.from_arrays([pa.array(texts)], names=["text"])
    x, rows = np.zeros((len(texts), mixing.WORDS)), 0
    for part in common.slices(batch, "text"):
        row, word, n, _ = mixing._word_counts(part)
        x[rows + row, word] = np.rint(mixing._vectors(row, word, n, model.rarity, len(part)) * mixing.STEPS)
        rows += len(part)
    x = x[x.any(axis=1)]
    own = (x @ model.centroids.T).argmax(axis=1)
    means = np.stack([x[own == k].sum(axis=0) for k in range(3)])
    assert len(x) == 6000 and np.allclose(means / np.linalg.norm(means, axis=1, keepdims=True), model.centroids, atol=1e-9)
    again = mixing.topics(docs.repartition(7), 3)
    assert (again.centroids == model.centroids).all() and (again.rarity == model.rarity).all()


def test_mixing_reads_each_text_once(spark):
    read = spark.sparkContext.accumulator(0)

    def seen(batches):
        for batch in batches:
            read.add(len(batch))
            yield batch

    kinds = "doc_id long, source string, lang string, text string"
    docs = spark.createDataFrame([(k, "s", "l", f"a{k % 3} b{k % 5} c{k % 7}") for k in range(300)], kinds).mapInArrow(seen, kinds)
    assert mixing.mixed(docs).count() == 300 and read.value == 300


def test_rounds_of_topics_read_packs_and_round_nothing(spark, monkeypatch):
    rng = np.random.default_rng(8)
    texts = [" ".join(f"{'abc'[k % 3]}{rng.integers(60)}" for _ in range(20)) for k in range(1500)]
    # texts of all sizes of vectors, one beyond a pack, copies among them, and one that fills several pieces
    texts += [" ".join(f"z{k}" for k in range(n)) for n in (1, 3000, 3000, 60000)] + ["", None]
    docs = spark.createDataFrame([(t,) for t in texts], "text string").repartition(2)
    kept, was = [], common.written
    monkeypatch.setattr(common, "written", lambda df: kept.append(was(df)) or kept[-1])
    monkeypatch.setattr(common, "removed", lambda df: None)
    model = mixing.topics(docs, 4)
    packs = kept[-1].toArrow()
    # several vectors to a row, none lost, and the rows short however many vectors there are
    size = np.frombuffer(b"".join(packs["size"].to_pylist()), np.int16)
    assert len(size) == 1504 and packs.num_rows < 1504 / 20 and max(map(len, packs["word"].to_pylist())) <= 2 * (mixing.ENTRIES + mixing.WORDS)
    word, value = (np.frombuffer(b"".join(packs[k].to_pylist()), np.int16) for k in ("word", "value"))
    x = np.zeros((len(size), mixing.WORDS), np.int64)
    x[np.repeat(np.arange(len(size)), size), word] = value
    # the same in whole numbers of any length
    exact = mixing._exact(model.centroids)
    parts = [[int(c * 2.0**60) for c in row] for row in exact.T]
    near = [[sum(int(row[w]) * part[w] for w in np.flatnonzero(row)) for part in parts] for row in x[::50]]
    batches = packs.to_batches()
    got = np.concatenate([mixing._likeness(at, w, v, exact) for at, w, v in mixing._unpacked(iter(batches))])[::50]
    assert all(g == h / 2**60 + low / 2**60 for row, wanted in zip(got, near, strict=True) for g, h, low in zip(row, wanted[:4], wanted[4:], strict=True))
    assert np.abs(exact.T[:4] + exact.T[4:] - model.centroids / (1 if np.linalg.norm(model.centroids, axis=1).max() <= 1 else 2)).max() < 1e-15
    assert list(mixing._unpacked(iter(batches[0].slice(0, 0) for _ in range(2)))) == []
