"""HTML extraction by site style trees.

The pages of a host are merged into one tree: a node for each path of elements (tag with its class and
id words), with the number of pages that show it, the spread of the child sequences in which it appears
(presentation) and the spread of the texts that stand in it (content). Both are entropies relative to
what the page count would allow: near 0 where every page shows the same, near 1 where every page differs.
All branches are judged, whatever they are called:

* one whose presentation and content are both below ``LOW`` goes from every page;
* one of low presentation whose content is below ``HIGH`` is filled from a stock that several pages draw
  from (menus, adverts, footers); outside of an article it goes from each page on which it holds what
  another page holds too.

Pages with the same article, or the same html, count once, and a branch that is or holds html, body,
main or article never goes for its importance. What the tree leaves, names may still take: elements
that say what they are (navigation, forms, adverts, comments), as reader comments differ on every page
and hosts of fewer than ``PAGES`` pages tell nothing. ``names=False`` leaves only the tree.

The tree is counted by grouped sums of (path, kind, value) over all pages, a path being a hash of its
host and its elements, so deep pages cost no more a node than flat ones; a hot host is one more set of
keys, pre-summed in every task. What is to be cut is sent out as hashes if there are at most ``SENT``;
else host block by host block.

Text of a page: of what is left, white space inside a block becomes one space, blocks are trimmed and
joined by line feeds; character references are decoded. Null or empty html gives an empty text, pages
that repeat are treated alike, a null or odd url puts a page on the host ""; pages of any length and
depth are read whole; extra columns are ignored.
"""

from __future__ import annotations

import html as html_lib
import re
from collections.abc import Iterator

import numpy as np
import pyarrow as pa
import xxhash
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from evigraph.llm import common

#: Least pages of a node before its entropy counts, importance below which a branch goes, content below
#: which what pages share goes, and hashes sent.
PAGES, LOW, HIGH, SENT = 8, 0.35, 0.95, 1_000_000

_TAG = re.compile(
    r"<!--.*?(?:-->|$)|<!\[CDATA\[.*?(?:\]\]>|$)|<[!?][^>]*(?:>|$)"
    r"|<(/?)([A-Za-z][^\s/>]*)((?:[^>\"'=]+|=\s*\"[^\"]*(?:\"|$)|=\s*'[^']*(?:'|$)|=|[\"'])*)(?:>|$)", re.S)
_ATTRIBUTE = re.compile(r"""([^\s=/"'>]+)(?:\s*=\s*(?:"([^"]*)"|'([^']*)'|([^\s"'>]+)))?""")
# fixed values of the HTML standard
VOID = frozenset("area base br col embed hr img input link meta param source track wbr".split())
RAW = frozenset("script style textarea title noscript template iframe noembed noframes xmp".split())
BLOCKS = frozenset(
    "address article aside blockquote body caption center dd details dialog dir div dl dt fieldset figcaption figure footer form h1 h2 h3 h4 h5 h6 head header hgroup hr html "
    "legend li main menu nav ol optgroup option p pre search section summary table tbody td tfoot th thead title tr ul".split())
CLOSES_P = BLOCKS - frozenset("body caption dd dt head html legend li optgroup option summary tbody td tfoot th thead title tr".split())
# what is never shown as text, and what stands around an article by its own tag
HIDDEN = frozenset("script style noscript template iframe head title textarea svg canvas object embed audio video map noembed noframes xmp datalist".split())
BESIDE = frozenset("nav footer aside form button select input label fieldset menu dialog search option optgroup".split())
_WORDS = re.compile(r"[a-z]+|[A-Z](?:[a-z]+|[A-Z]*(?![a-z]))|[0-9]+")
# words of class, id and role that name what stands around an article
AROUND = frozenset(
    "ad ads adv advert advertisement advertising adsense banner sponsor sponsored promo promoted promotion nav navbar navigation menu menubar breadcrumb breadcrumbs sidebar aside rail "
    "footer foot masthead topbar toolbar cookie cookies consent gdpr notice notices alert popup modal overlay newsletter subscribe subscription signup login share sharing social follow "
    "comment comments disqus respond reply replies discussion related recommended recommendations widget pagination pager search copyright legal disclaimer contentinfo complementary "
    "skip toc tags tagcloud login paywall toast".split())
HEADINGS = frozenset("h1 h2 h3 h4 h5 h6".split())
# what importance never cuts
FRAME = frozenset("html body main article".split())


class Node:
    __slots__ = ("tag", "name", "key", "around", "children", "parent", "article", "frame", "digest")

    def __init__(self, tag: str, name: str, key: int, around: bool, parent: Node | None, article: bool):
        self.tag, self.name, self.key, self.around, self.parent, self.article = tag, name, key, around, parent, article
        self.children: list[Node | str] = []
        self.frame, self.digest = False, 0


def _child(parent: Node, tag: str, name: str, around: bool) -> Node:
    key = xxhash.xxh3_64_intdigest(name, seed=parent.key)
    node = Node(tag, name, key, around, parent, parent.article or tag in ("article", "main"))
    parent.children.append(node)
    return node


def _named(tag: str, attributes: str) -> tuple[str, bool]:
    """The node's name in the tree, and whether it says to stand around an article."""
    words: list[str] = []
    hidden = False
    for name, a, b, c in _ATTRIBUTE.findall(attributes):
        name, value = name.lower(), a or b or c
        if name in ("class", "id", "role"):
            words += [w.lower() for w in _WORDS.findall(value)]
        elif name == "hidden" or name == "aria-hidden" and value == "true" or name == "style" and re.search(r"display\s*:\s*none", value):
            hidden = True
    kept = [w for w in words if not w.isdigit()]
    return ".".join([tag, *sorted(set(kept))]), hidden or any(w in AROUND for w in kept)


def parse(source: str, host: str = "") -> Node:
    """A forgiving DOM: implied ends of paragraphs, items and cells, unclosed and stray tags allowed."""
    root = here = Node("", "", xxhash.xxh3_64_intdigest(host), False, None, False)
    open_tags: dict[str, int] = {}
    at, raw = 0, None

    def leave(x: Node) -> Node:
        """Close ``here`` up to and with ``x``."""
        y = here
        while y is not x.parent:
            open_tags[y.tag] -= 1
            y = y.parent
        return y

    for m in _TAG.finditer(source):
        if raw:
            if not (m[2] and m[1] and m[2].lower() == raw):
                continue
        if m.start() > at:
            here.children.append(source[at : m.start()] if raw else html_lib.unescape(source[at : m.start()]))
        at, raw = m.end(), None
        if not m[2]:
            continue
        tag = m[2].lower()
        if m[1]:
            if open_tags.get(tag):
                x = here
                while x.tag != tag:
                    # the end of an inline element does not close the blocks around it
                    if tag not in BLOCKS and x.tag in BLOCKS:
                        break
                    x = x.parent
                if x.tag == tag:
                    here = leave(x)
            elif tag == "p":
                _child(here, "p", "p", False)
            continue
        ends = _ENDS.get(tag, ()) + (("p",) if tag in CLOSES_P else ())
        if any(open_tags.get(t) for t in ends):
            stops = _STOPS.get(tag, _P_STOPS)
            x = here
            while x is not root and x.tag not in stops:
                if x.tag in ends:
                    up = x.parent
                    here = leave(x)
                    if tag != "tr" or x.tag == "tr":
                        break
                    x = up
                    continue
                x = x.parent
        name, around = _named(tag, m[3] or "")
        node = _child(here, tag, name, around)
        if tag in FRAME:
            x = node
            while x is not None and not x.frame and not (hidden(x) or named(x)):
                x.frame, x = True, x.parent
        if tag not in VOID:
            open_tags[tag] = open_tags.get(tag, 0) + 1
            here = node
            if tag in RAW and not (m[3] or "").rstrip().endswith("/"):
                raw = tag
    if at < len(source):
        here.children.append(source[at:] if raw else html_lib.unescape(source[at:]))
    return root


_ENDS = {"li": ("li",), "dt": ("dt", "dd"), "dd": ("dt", "dd"), "tr": ("tr", "td", "th"), "td": ("td", "th"), "th": ("td", "th"), "option": ("option",), "tbody": ("tr", "td", "th"), "thead": (), "tfoot": ("tr", "td", "th")}
_STOPS = {"li": ("ul", "ol", "menu"), "dt": ("dl",), "dd": ("dl",), "tr": ("table",), "td": ("tr", "table"), "th": ("tr", "table"), "option": ("select",), "tbody": ("table",), "tfoot": ("table",)}
_P_STOPS = ("table", "td", "th", "button", "div", "article", "section")


def hidden(node: Node) -> bool:
    """Whether the element's text is never shown."""
    return node.tag in HIDDEN


def named(node: Node) -> bool:
    """Whether the element says itself that it stands around the article."""
    if node.tag in BESIDE:
        return True
    if node.tag == "header":
        return not node.article
    return node.around and node.tag not in FRAME


def nodes(root: Node) -> list[Node]:
    """The elements that are shown, with the digest of the text of each one's whole branch, so a branch
    is important if anything in it is."""
    order, todo = [], [root]
    while todo:
        x = todo.pop()
        order.append(x)
        todo += [c for c in x.children if isinstance(c, Node) and not hidden(c)]
    for x in reversed(order):
        own = " ".join(" ".join(c for c in x.children if isinstance(c, str)).split())
        value = ",".join([str(c.digest) for c in x.children if isinstance(c, Node) and not hidden(c)]) + own
        x.digest = xxhash.xxh3_64_intdigest(value) if value.strip("0,") else 0
    return order[1:]


def _by_path(found: list[Node]) -> dict[int, tuple[str, int, bool]]:
    """(style, content, inside an article) of each path of a page; elements of one path go together."""
    seen: dict[int, tuple[list[str], list[str], bool]] = {}
    for x in found:
        s = seen.setdefault(x.key, ([], [], x.article))
        s[0].append(",".join(c.name for c in x.children if isinstance(c, Node) and not hidden(c)))
        s[1].append(str(x.digest))
    return {k: ("\1".join(a), xxhash.xxh3_64_intdigest("\1".join(b)), c) for k, (a, b, c) in seen.items()}


def _signed(x: int) -> int:
    return x - (1 << 63)


def _value_key(path: int, content: int) -> int:
    return xxhash.xxh3_64_intdigest(content.to_bytes(8, "little"), seed=path)


def main_text(root: Node, cut, names: bool = True) -> str:
    """The blocks of what is left once hidden, unimportant and named branches are gone. ``cut`` tells of a
    branch whether it is unimportant."""
    blocks: list[str] = []
    run: list[str] = []

    def flush() -> None:
        s = " ".join("".join(run).split())
        run.clear()
        if s:
            blocks.append(s)

    stack: list[tuple[Node, int]] = [(root, 0)]
    while stack:
        x, k = stack.pop()
        if k == 0 and x.tag in BLOCKS:
            flush()
        moved = False
        for i in range(k, len(x.children)):
            c = x.children[i]
            if isinstance(c, str):
                run.append(c)
            elif c.tag == "br":
                run.append(" ")
            elif not hidden(c) and (c.frame or not cut(c)) and not (names and named(c)):
                stack.append((x, i + 1))
                stack.append((c, 0))
                moved = True
                break
            elif c.tag in BLOCKS:
                flush()
        if not moved and x.tag in BLOCKS:
            flush()
    flush()
    return "\n".join(blocks)


def page_text(source: str | None, host: str, held: set[int] | frozenset[int] = frozenset(), names: bool = True) -> str:
    root = parse(source or "", host)
    if not held:
        return main_text(root, lambda c: False, names)
    paths = _by_path(nodes(root))

    def cut(c: Node) -> bool:
        return _signed(c.key) in held or not c.article and c.key in paths and _signed(_value_key(c.key, paths[c.key][1])) in held

    return main_text(root, cut, names)


def host_of(url: str | None) -> str:
    return re.split(r"[/?#]", url.partition("://")[2], maxsplit=1)[0].lower() if url and "://" in url else ""


def _host():
    return F.lower(F.regexp_extract(F.coalesce("url", F.lit("")), "://([^/?#]*)", 1))


def counted(pages: DataFrame) -> DataFrame:
    """(path, content, value, article, n): on how many pages of different articles each path of a host has
    a style (content false) or a text (content true)."""
    def count(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in batches:
            rows: set[tuple[int, bool, int, bool, int]] = set()
            for url, source in zip(*(batch.column(c).to_pylist() for c in ("url", "html")), strict=True):
                root = parse(source or "", host_of(url))
                page = _signed(xxhash.xxh3_64_intdigest(main_text(root, lambda c: False)))
                for path, (style, content, article) in _by_path(nodes(root)).items():
                    rows.add((_signed(path), False, _signed(xxhash.xxh3_64_intdigest(style)), article, page))
                    rows.add((_signed(path), True, _signed(_value_key(path, content)), article, page))
            cols = list(zip(*rows, strict=True)) or [(), (), (), (), ()]
            kinds = (pa.int64(), pa.bool_(), pa.int64(), pa.bool_(), pa.int64())
            yield pa.RecordBatch.from_arrays([pa.array(c, k) for c, k in zip(cols, kinds, strict=True)], names=["path", "content", "value", "article", "page"])

    rows = pages.select("url", "html").mapInArrow(count, "path long, content boolean, value long, article boolean, page long").distinct()
    return rows.groupBy("path", "content", "value", "article").agg(F.count("*").alias("n"))


def importance(counts: DataFrame) -> DataFrame:
    """(path, article, pages, presentation, content) of every node of the hosts' trees."""
    n = F.col("n").cast("double")
    spread = counts.groupBy("path", "article", "content").agg(F.sum("n").alias("pages"), (F.log(F.sum(n)) - F.sum(n * F.log(n)) / F.sum(n)).alias("h"))
    share = F.when(F.col("pages") > 1, F.col("h") / F.log(F.col("pages").cast("double"))).otherwise(1.0)
    of = lambda c: F.max(F.when(F.col("content") == c, share))
    return spread.groupBy("path", "article").agg(F.max("pages").alias("pages"), of(False).alias("presentation"), of(True).alias("content"))


def cuts(pages: DataFrame, low: float = LOW, high: float = HIGH, least: int = PAGES) -> DataFrame:
    """key: paths that go from every page, and of stock-filled ones what several pages hold."""
    counts = common.written(counted(pages))
    nodes_of = importance(counts).filter((F.col("pages") >= least) & (F.col("presentation") < low))
    whole = nodes_of.filter(F.col("content") < low).select(F.col("path").alias("key"))
    stocked = nodes_of.filter(~F.col("article") & (F.col("content") >= low) & (F.col("content") < high)).select("path")
    shared = counts.filter(F.col("content") & ~F.col("article") & (F.col("n") > 1)).join(stocked, "path", "left_semi").select(F.col("value").alias("key"))
    return whole.unionByName(shared)


def extracted(pages: DataFrame, low: float = LOW, high: float = HIGH, least: int = PAGES, sent: int = SENT, names: bool = True) -> DataFrame:
    """page_id, url, text, n_chars."""
    cut = common.written(cuts(pages, low, high, least))
    kinds = dict(pages.dtypes)
    schema = f"page_id {kinds['page_id']}, url string, text string, n_chars long"
    if common.small(cut, sent):
        parts = [(pages, np.array([r["key"] for r in cut.collect()], np.int64))]
    else:  # too many to send at once: each block of hosts gets the keys of its own trees
        n = 2 * -(-cut.count() // max(1, sent))
        block = F.pmod(F.xxhash64(_host()), F.lit(n))
        parts = []
        for k in range(n):
            own = pages.filter(block == k)
            parts.append((own, np.array([r["key"] for r in cuts(own, low, high, least).collect()], np.int64)))

    def run_with(keys: np.ndarray):
        def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
            held = set(keys.tolist())
            for batch in batches:
                texts = [page_text(source, host_of(url), held, names) for url, source in zip(batch.column("url").to_pylist(), batch.column("html").to_pylist(), strict=True)]
                yield pa.RecordBatch.from_arrays([batch.column("page_id"), batch.column("url"), pa.array(texts, pa.string()), pa.array([len(t) for t in texts], pa.int64())], names=["page_id", "url", "text", "n_chars"])

        return run

    out = [p.select("page_id", "url", "html").mapInArrow(run_with(k), schema) for p, k in parts]
    united = out[0]
    for x in out[1:]:
        united = united.unionByName(x)
    return united
