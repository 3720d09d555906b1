"""Main text of web pages by wrapper induction.

The pages of a host are parsed to DOM trees, and each is aligned by simple tree matching with one page of the host, the one with the
median number of tags.  What stands at a node of that tree on most different pages is template.  The rest varies, and its weight, the
characters that are no link, tells where the article is: from the root down, the way goes into the part that holds most of the
varying text.  So varying menus, adverts and notices fall out with the constant ones, without any list of names.  A page's text is what varies
in the slots of that part.

HTML's own elements that are no text or no article (scripts, menus, forms, footers) and what is hidden never count.  Class names and ids are asked in three places
only: adverts and readers' comments inside the part chosen, hosts where no part holds most of the varying text, and hosts of fewer than three different
pages, which cannot be aligned.  Names are read as a whole: entry-header, social-history and copyright-reform are no header, sharing box or footer.

All pages of a host count, whatever their number: chunks of pages are aligned with the one reference, and what they
saw is summed up in a shuffle of node numbers and hashes.  Runs of siblings with one structure are folded to one repeated node before matching, which makes trees
small.  Nothing recurses and tags are found in one pass, so trees may be of any depth and pages of any length.

Edge cases: NULL or empty html has an empty text; a NULL url belongs to the host with an empty name; pages with the same three longest texts are copies and count
once; a page on which all of the article's part is template is a copy of others, and keeps its text; unclosed and crossed tags are closed by the next block;
repeated rows and NULL page_ids are rows of their own; an empty table gives an empty result; other columns are ignored.
"""

from __future__ import annotations

import re
from collections import Counter
from collections.abc import Iterator
from dataclasses import dataclass, field
from functools import lru_cache
from hashlib import blake2b
from html import unescape

import pyarrow as pa
from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

from depstrata.llm.common import staged

# HTML's elements without content, blocks, and names of what is no article.
VOID = frozenset("area base br col embed hr img input link meta param source track wbr".split())
BLOCKS = frozenset(
    "address article aside blockquote body caption dd details dialog div dl dt fieldset figcaption figure footer form h1 h2 h3 h4 h5 h6 "
    "head header hgroup hr html legend li main menu nav ol p pre section summary table tbody td tfoot th thead title tr ul".split()
)
RAW = frozenset("script style textarea title noscript template iframe xmp".split())
NEVER = frozenset("script style nav footer aside form noscript template iframe svg button select textarea input head title menu dialog object canvas audio video".split())
#: Names that are never an article's, also inside one; alone or with words of LAYOUT, so that ad-slot is one and ad-hoc-networks is not.
CLEAR = frozenset("ad ads advert adverts advertisement advertisements adsbygoogle sponsored comments commentlist disqus breadcrumb breadcrumbs pagination navbar".split())
CLEAR_WHOLE = frozenset("comment-list comment-form comment-respond disqus-thread share-bar share-buttons share-links sharing-buttons social-buttons social-links social-share related-posts related-articles newsletter-signup".split())
#: Names of what stands around an article, on pages that mark none.
AROUND = CLEAR | frozenset(
    "sponsor promo banner sidebar menu nav navigation footer masthead cookie cookies consent gdpr popup modal overlay newsletter subscribe signup login comment "
    "share sharing social related recommended pager toolbar skip widget widgets copyright".split()
)
AROUND_WHOLE = CLEAR_WHOLE | frozenset("header site-header global-header main-header top-header".split())
LAYOUT = frozenset("site global main top bottom left right inner outer primary secondary block box area wrap wrapper container slot unit row col list item items bar link links button buttons icon icons desktop mobile fixed sticky".split())
ROLES = frozenset("navigation banner contentinfo complementary search form dialog alert menu menubar alertdialog".split())
#: An element that opens ends an open paragraph or item of these.
CLOSES = {"li": {"li"}, "dt": {"dt", "dd"}, "dd": {"dt", "dd"}, "tr": {"tr", "td", "th"}, "td": {"td", "th"}, "th": {"td", "th"}, "option": {"option"}}

#: Elements that hold parts of a page rather than a run of text.
PARTS = frozenset("html body div section article main center table tbody tr td".split())

_TAG = re.compile(r"/?[a-zA-Z][^\s/>]*+")
_STOP = re.compile("[>\"']")
_ATTR = re.compile(r"(class|id|role|hidden|aria-hidden|style)(?:\s*=\s*(?:\"([^\"]*)\"|'([^']*)'|([^\s>]+)))?(?=[\s/]|$)", re.I)
_NAME = re.compile(r"[A-Za-z]+")
_NO_DIGITS = {ord(d): None for d in "0123456789"}


class Node:
    __slots__ = ("tag", "label", "children", "blocks", "repeat", "shape", "count")

    def __init__(self, tag: str, label: str):
        self.tag, self.label = tag, label
        self.children: list[Node] = []
        self.blocks: list[int] = []  # numbers of the blocks whose text starts here
        self.repeat = 1  # siblings that were folded to this node
        self.shape = b""  # digest of the labels of the tree below
        self.count = 0  # its nodes


def _named(word: str, names: frozenset[str], whole: frozenset[str]) -> bool:
    """Whether a class name or id, as a whole, is one of what is no article."""
    parts = _NAME.findall(word)
    return "-".join(parts) in whole or (not names.isdisjoint(parts) and all(x in names or x in LAYOUT for x in parts))


#: Why an element is no article: by HTML itself, by a name that leaves no doubt, by a name of what stands around.
NO_TEXT, NO_DOUBT, OUTSIDE = 1, 2, 4


@lru_cache(65536)
def _element(tag: str, attrs: str, in_article: bool) -> tuple[str, int]:
    """Label of an element, and the reasons against it as bits."""
    why, label = NO_TEXT * (tag in NEVER or (tag == "header" and not in_article)), tag
    for name, a, b, c in _ATTR.findall(attrs) if attrs else ():
        name, value = name.lower(), (a or b or c).lower()
        if name == "class":
            label = f"{tag}.{value.translate(_NO_DIGITS)}"
        if name in ("class", "id"):
            for word in value.split() if tag not in ("html", "body", "article", "main") else ():
                why |= NO_DOUBT * _named(word, CLEAR, CLEAR_WHOLE) | OUTSIDE * _named(word, AROUND, AROUND_WHOLE)
        elif name == "role":
            why |= NO_TEXT * (value in ROLES)
        elif name == "hidden" or (name == "aria-hidden" and value == "true") or (name == "style" and "display:none" in value.replace(" ", "")):
            why |= NO_TEXT
    return label, why


def _tags(html: str) -> Iterator[tuple[int, int, str, str]]:
    """(start, end, name with / if it closes, attributes) of the tags of a page, and comments with an empty name; the receiver may send a place to go on from.

    A > in quotes ends no tag.  Where quotes do not match so that no end is left, the first > ends this and all further tags.
    """
    pos, quotes = 0, {q: html.rfind(q) for q in "\"'"}
    strict = True
    while (at := html.find("<", pos)) >= 0:
        if html.startswith(("!", "?"), at + 1):
            mark = "-->" if html.startswith("!--", at + 1) else ">"
            end = html.find(mark, at + 2)
            end = len(html) if end < 0 else end + len(mark)
            pos = (yield at, end, "", "") or end
            continue
        m = _TAG.match(html, at + 1)
        if not m:
            pos = at + 1
            continue
        end, look = -1, m.end()
        while strict and (stop := _STOP.search(html, look)):
            look = stop.end()
            if stop[0] == ">":
                end = look
                break
            if stop.start() < quotes[stop[0]]:
                look = html.find(stop[0], look) + 1
        if end < 0:
            strict = False
            end = html.find(">", m.end()) + 1
            if not end:
                return
        pos = (yield at, end, m[0].lower(), html[m.end() : end - 1]) or end


class Page:
    """Tree and blocks of one page."""

    def __init__(self, html: str):
        self.root = Node("#root", "#root")
        self.texts: list[str] = []
        self.why: list[int] = []  # reasons against the block, of all elements around it
        self.inside: list[bool] = []  # in an element that marks the article
        self.prose: list[int] = []  # characters that are no link
        # An open element: node, reasons of it and all around it, links and articles around it.
        stack: list[tuple[Node, int, int, int]] = [(self.root, 0, 0, 0)]
        buffer: list[str] = []
        linked = 0
        owner = stack[-1]
        opened: Counter = Counter()

        def flush() -> None:
            nonlocal linked
            raw = "".join(buffer)
            text = " ".join(unescape(raw).split())
            if text:
                owner[0].blocks.append(len(self.texts))
                self.texts.append(text)
                self.why.append(owner[1])
                self.inside.append(bool(owner[3]))
                self.prose.append(len(text) * (len(raw) - linked) // len(raw))
            buffer.clear()
            linked = 0

        def add(text: str) -> None:
            nonlocal owner, linked
            if text:
                if not buffer:
                    owner = stack[-1]
                buffer.append(text)
                if stack[-1][2]:
                    linked += len(text)

        def cut(depth: int) -> None:
            for n, *_ in stack[depth:]:
                opened[n.tag] -= 1
            del stack[depth:]

        pos = 0
        tags = _tags(html)
        found = next(tags, None)
        while found:
            at, end, name, attrs = found
            add(html[pos:at])
            pos, go_on = end, None
            tag = name.lstrip("/")
            if name.startswith("/"):
                if opened[tag]:
                    depth = next(i for i in range(len(stack) - 1, -1, -1) if stack[i][0].tag == tag)
                    if stack[-1][1] or any(n.tag in BLOCKS for n, *_ in stack[depth:]):
                        flush()
                    cut(depth)
                elif tag in BLOCKS:
                    flush()
            elif name:
                _, around, links, article = stack[-1]
                label, why = _element(tag, attrs.strip(), bool(article))
                if tag in BLOCKS or (why & ~around):
                    flush()
                    # A block ends what was left open in a line, but for what is dropped as a whole, and an open paragraph.
                    while tag in BLOCKS and len(stack) > 1 and stack[-1][0].tag not in BLOCKS and not stack[-1][1]:
                        cut(len(stack) - 1)
                    for k in range(len(stack) - 1, 0, -1) if not stack[-1][1] else ():
                        if stack[k][0].tag == "p" or stack[k][0].tag in CLOSES.get(tag, ()):
                            cut(k)
                            break
                        if stack[k][0].tag in BLOCKS:
                            break
                    _, around, links, article = stack[-1]
                if tag == "br":
                    add(" ")
                if tag not in VOID and (not attrs.endswith("/") or tag in BLOCKS):
                    node = Node(tag, label)
                    stack[-1][0].children.append(node)
                    stack.append((node, around | why, links + (tag == "a"), article + (tag in ("article", "main"))))
                    opened[tag] += 1
                    if tag in RAW:
                        close = _raw_end(tag).search(html, pos)
                        add(html[pos : close.start() if close else len(html)])
                        flush()
                        cut(len(stack) - 1)
                        pos = go_on = close.end() if close else len(html)
            found = next(tags, None) if go_on is None else _send(tags, go_on)
        add(html[pos:])
        flush()
        _fold(self.root)


@lru_cache(64)
def _raw_end(tag: str) -> re.Pattern:
    return re.compile(rf"</{tag}\s*+>", re.I)


def _send(tags: Iterator, pos: int):
    try:
        return tags.send(pos)
    except StopIteration:
        return None


def _fold(root: Node) -> None:
    """Fold runs of siblings of one shape to one node, bottom up, and set the shapes."""
    for node in reversed(_listed(root)):
        out: list[Node] = []
        for c in node.children:
            if out and out[-1].shape == c.shape:
                _absorb(out[-1], c)
            else:
                out.append(c)
        node.children = out
        label = node.label.encode("utf-8", "surrogatepass")
        node.shape = blake2b(b"%d:%b" % (len(label), label) + b"".join(c.shape for c in out), digest_size=16).digest()
        node.count = 1 + sum(c.count for c in out)


def _absorb(into: Node, other: Node) -> None:
    into.repeat += other.repeat
    todo = [(into, other)]
    for a, b in todo:
        a.blocks += b.blocks
        todo += zip(a.children, b.children)


def _listed(node: Node) -> list[Node]:
    out = [node]
    for n in out:
        out.extend(n.children)
    return out


def match(a: Node, b: Node) -> tuple[int, list[tuple[Node, Node]]]:
    """Simple tree matching: size of the largest order-preserving matching of two trees, and its pairs."""
    size: dict[tuple[int, int], int] = {}
    chosen: dict[tuple[int, int], list[tuple[Node, Node]]] = {}
    todo = [(a, b, False)]
    while todo:
        x, y, ready = todo.pop()
        at = id(x), id(y)
        if x.label != y.label or x.shape == y.shape:
            size[at] = x.count if x.label == y.label else 0
        elif not ready:
            todo.append((x, y, True))
            todo += [(c, d, False) for c in x.children for d in y.children]
        else:
            size[at], chosen[at] = _best(x.children, y.children, size)
    pairs, left = [], [(a, b)] if size[id(a), id(b)] else []
    for x, y in left:
        if x.shape == y.shape:
            pairs += zip(_listed(x), _listed(y))
        else:
            pairs.append((x, y))
            left += chosen[id(x), id(y)]
    return size[id(a), id(b)], pairs


def _best(xs: list[Node], ys: list[Node], size: dict[tuple[int, int], int]) -> tuple[int, list[tuple[Node, Node]]]:
    """Size of a matching of two nodes by the sizes of their children's, and the children that are matched."""
    m, n = len(xs), len(ys)
    best = [[0] * (n + 1) for _ in range(m + 1)]
    for i, x in enumerate(xs):
        for j, y in enumerate(ys):
            best[i + 1][j + 1] = max(best[i][j + 1], best[i + 1][j], best[i][j] + size.pop((id(x), id(y))))
    pairs, i, j = [], m, n
    while i and j:
        if best[i][j] == best[i - 1][j]:
            i -= 1
        elif best[i][j] == best[i][j - 1]:
            j -= 1
        else:
            i, j = i - 1, j - 1
            pairs.append((xs[i], ys[j]))
    return best[m][n] + 1, pairs


class Reference:
    """A page to align others with.  Pages of one shape are matched once."""

    def __init__(self, html: str):
        self.page = Page(html)
        self.known: dict[bytes, list[int]] = {}

    def align(self, page: Page) -> list[int]:
        listed = _listed(page.root)
        if page.root.shape not in self.known:
            if len(self.known) >= 4096:
                self.known.clear()
            number = {id(n): i for i, n in enumerate(_listed(self.page.root))}
            place = {id(y): number[id(x)] for x, y in match(self.page.root, page.root)[1]}
            at: dict[int, int] = {}
            for node in listed:  # parents come first
                mine = at[id(node)] = place.get(id(node), at.get(id(node), 0))
                at.update((id(c), mine) for c in node.children)
            self.known[page.root.shape] = [at[id(n)] for n in listed]
        out = [0] * len(page.texts)
        for node, x in zip(listed, self.known[page.root.shape]):
            for b in node.blocks:
                out[b] = x
        return out


@dataclass
class Wrapper:
    """What is learnt of a host: weight of the varying text and the template texts (hashes) of the nodes of its reference."""

    weight: dict[int, int] = field(default_factory=dict)
    template: dict[int, frozenset[int]] = field(default_factory=dict)
    part: frozenset[int] | None = None  # nodes of the part that holds the article; None if none stands out

    def choose(self, ref: Page, share: float) -> Wrapper:
        nodes = _listed(ref.root)
        number = {id(n): i for i, n in enumerate(nodes)}
        total = [self.weight.get(i, 0) for i in range(len(nodes))]
        for i in reversed(range(len(nodes))):
            total[i] += sum(total[number[id(c)]] for c in nodes[i].children)
        at, sure = 0, False
        while total[at]:
            best = max((number[id(c)] for c in nodes[at].children), key=lambda c: (total[c], -c), default=at)
            if best == at or nodes[best].tag not in PARTS or nodes[best].repeat > 1 or total[best] < share * total[at]:
                break
            # Much text right in this part, or in elements that other pages lack, is the article's as well.
            if 2 * self.weight.get(at, 0) > (1 - share) * total[at]:
                break
            sure |= total[best] < total[at] or nodes[best].tag in ("article", "main")
            at = best
        self.part = frozenset(number[id(n)] for n in _listed(nodes[at])) if at and (sure or nodes[at].tag not in ("html", "body")) else None
        return self


def text_hash(text: str) -> int:
    return int.from_bytes(blake2b(text.encode("utf-8", "surrogatepass"), digest_size=8).digest(), "big", signed=True)


def page_key(page: Page) -> int:
    """Equal for copies: a hash of the three longest texts."""
    return text_hash("\n".join(sorted((t for t, w in zip(page.texts, page.why) if not w & NO_TEXT), key=lambda t: (-len(t), t))[:3]))


def observe(ref: Reference, html: str | None) -> list[tuple[int, int, int, int]]:
    """(node, text hash, page key, prose characters) of the blocks of a page."""
    page = Page(html or "")
    key = page_key(page)
    return [(x, text_hash(t), key, n) for x, t, w, n in zip(ref.align(page), page.texts, page.why, page.prose) if not w & NO_TEXT]


def apply(html: str | None, ref: Reference | None, wrapper: Wrapper | None) -> str:
    """Main text of a page; without a wrapper by names."""
    page = Page(html or "")
    kept = [i for i, w in enumerate(page.why) if not w & (NO_TEXT | NO_DOUBT)]
    if wrapper is None or wrapper.part is None:
        inside = [i for i in kept if page.inside[i]]
        kept = inside or [i for i in kept if not page.why[i] & OUTSIDE]
    if wrapper is not None and ref is not None:
        at = ref.align(page)
        if wrapper.part is not None:
            kept = [i for i in kept if at[i] in wrapper.part]
        own = [i for i in kept if text_hash(page.texts[i]) not in wrapper.template.get(at[i], ())]
        kept = own or kept
    return "\n\n".join(page.texts[i] for i in kept)


#: Share of a host's different pages on which a text is template, least number of them, and share of the varying text that the article's part holds.
CONSTANT, LEAST_PAGES, DOMINANT = 0.6, 3, 0.6


def extract(pages: list[str | None], constant: float = CONSTANT, least_pages: int = LEAST_PAGES, dominant: float = DOMINANT) -> list[str]:
    """Main texts of the pages of one host, without Spark; main_text() gives the same."""
    size = {p: len(p) - len(p.replace("<", "")) for p in {p or "" for p in pages}}
    median = sorted(size.values())[(len(size) - 1) // 2] if size else 0
    ref = Reference(min(((abs(n - median), text_hash(p), p) for p, n in size.items()), default=(0, 0, ""))[2])
    seen = {row for p in pages for row in observe(ref, p)}
    n_pages = len({key for _, _, key, _ in seen})
    if n_pages < least_pages:
        return [apply(p, None, None) for p in pages]
    times = Counter((x, h) for x, h, _ in {r[:3] for r in seen})
    prose = {(x, h): n for x, h, _, n in seen}
    wrapper, template = Wrapper(), {}
    for (x, h), k in times.items():
        if k >= max(least_pages, constant * n_pages):
            template.setdefault(x, set()).add(h)
        else:
            wrapper.weight[x] = wrapper.weight.get(x, 0) + k * prose[x, h]
    wrapper.template = {x: frozenset(h) for x, h in template.items()}
    wrapper.choose(ref.page, dominant)
    return [apply(p, ref, wrapper) for p in pages]


def _rows(batch: pa.RecordBatch, *names: str) -> Iterator[tuple]:
    return zip(*(batch.column(batch.schema.get_field_index(n)) for n in names))


class _References:
    """The references of the hosts met last, parsed."""

    def __init__(self, most: int = 256):
        self.held: dict[str, object] = {}
        self.most = most

    def get(self, host: str, make):
        if host not in self.held:
            if len(self.held) >= self.most:
                self.held.clear()
            self.held[host] = make()
        return self.held[host]


def _small(df: DataFrame, size: Column, bound: int) -> DataFrame:
    """Marked for a broadcast if all of it has at most so many bytes; else joined by sorting, where skewed hosts are split."""
    total = df.agg(F.sum(size).alias("n")).first().n or 0
    return F.broadcast(df) if total <= bound else df


def references(rows: DataFrame, least_pages: int = LEAST_PAGES, max_broadcast: int = 32 << 20) -> DataFrame:
    """host, reference: of each host a page with the median number of tags, that with the smallest hash; copies of a page count once."""
    tags = F.length("html") - F.length(F.replace("html", F.lit("<"), F.lit("")))
    slim = rows.select("host", tags.alias("tags"), F.xxhash64("html").alias("hash")).distinct()
    # A host has as many rows from here on as its pages have different numbers of tags.
    slim = staged(slim.groupBy("host", "tags").agg(F.count("*").alias("n"), F.min("hash").alias("hash")), "page-sizes")
    middle = slim.groupBy("host").agg(F.floor(F.percentile("tags", F.lit(0.5), F.col("n"))).alias("median"), F.sum("n").alias("pages"))
    middle = middle.where(F.col("pages") >= least_pages)  # copies of pages never make three different ones
    near = slim.join(middle, "host").groupBy("host").agg(F.min(F.struct(F.abs(F.col("tags") - F.col("median")), "hash")).alias("m"))
    picked = staged(near.select(F.col("host").alias("of"), F.col("m.hash").alias("is")), "picked")
    picked = _small(picked, F.length("of") + 32, max_broadcast)
    found = rows.join(picked, (F.col("host") == F.col("of")) & (F.xxhash64("html") == F.col("is")))
    return staged(found.groupBy("host").agg(F.min("html").alias("reference")), "references")


def wrappers(rows: DataFrame, refs: DataFrame, constant: float = CONSTANT, least_pages: int = LEAST_PAGES) -> DataFrame:
    """host, nodes: (node, weight, template text hashes) of hosts of at least so many different pages."""
    schema = "host string, node int, text long, page long, prose long"

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        refs = _References()
        for batch in batches:
            for at in range(0, batch.num_rows, 512):
                out: list[tuple] = []
                for host, ref, html in _rows(batch.slice(at, 512), "host", "reference", "html"):
                    name = host.as_py()
                    reference = refs.get(name, lambda: Reference(ref.as_py()))  # noqa: B023
                    out += [(name, *row) for row in set(observe(reference, html.as_py()))]
                if out:
                    types = (pa.string(), pa.int32(), pa.int64(), pa.int64(), pa.int64())
                    yield pa.RecordBatch.from_arrays([pa.array(c, t) for c, t in zip(zip(*out), types)], names=["host", "node", "text", "page", "prose"])

    seen = rows.select("host", "html").join(refs, "host").select("host", "reference", "html").mapInArrow(run, schema)
    # Copies of a page and repeated texts of one page count once.
    seen = staged(seen.groupBy("host", "node", "text", "page").agg(F.min("prose").alias("prose")), "page-texts")
    hosts = seen.groupBy("host").agg(F.count_distinct("page").alias("pages")).where(F.col("pages") >= least_pages)
    texts = seen.groupBy("host", "node", "text").agg(F.count("*").alias("times"), F.min("prose").alias("prose")).join(hosts, "host")
    common = F.col("times") >= F.greatest(F.lit(least_pages), F.col("pages") * constant)
    # A node has at most 1 / constant times the texts of a page as template.
    nodes = texts.groupBy("host", "node").agg(F.sum(F.when(~common, F.col("times") * F.col("prose")).otherwise(0)).alias("weight"), F.collect_list(F.when(common, F.col("text"))).alias("template"))
    return staged(nodes.groupBy("host").agg(F.collect_list(F.struct("node", "weight", "template")).alias("nodes")), "wrappers")


def main_text(pages: DataFrame, constant: float = CONSTANT, least_pages: int = LEAST_PAGES, dominant: float = DOMINANT, max_broadcast: int = 32 << 20) -> DataFrame:
    """page_id, url, text, n_chars; one row for each page.

    References and wrappers are broadcast while all of them have at most max_broadcast bytes.
    """
    host = F.lower(F.regexp_extract(F.coalesce(F.col("url").cast("string"), F.lit("")), r"^[A-Za-z][A-Za-z0-9+.-]*://([^/:?#]*)", 1))
    rows = pages.select(
        F.col("page_id").cast("long").alias("page_id"), F.col("url").cast("string").alias("url"), host.alias("host"), F.coalesce(F.col("html").cast("string"), F.lit("")).alias("html")
    )
    refs = references(rows, least_pages, max_broadcast)
    learnt = wrappers(rows, _small(refs, F.length("reference"), max_broadcast), constant, least_pages)
    learnt = learnt.join(_small(refs, F.length("reference"), max_broadcast), "host").select(F.col("host").alias("of"), "reference", "nodes")
    size = F.length("reference") + F.aggregate("nodes", F.lit(0), lambda n, x: n + 16 + 8 * F.size(x["template"]))
    both = rows.join(_small(learnt, size, max_broadcast), F.col("host") == F.col("of"), "left").select("page_id", "url", "html", "host", "reference", "nodes")

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        known = _References()

        def wrapper(ref: pa.Scalar, nodes: pa.Scalar) -> tuple[Reference, Wrapper]:
            reference, w = Reference(ref.as_py()), Wrapper()
            for n in nodes.as_py():
                w.weight[n["node"]], w.template[n["node"]] = n["weight"], frozenset(n["template"])
            return reference, w.choose(reference.page, dominant)

        for batch in batches:
            for at in range(0, batch.num_rows, 512):
                part = batch.slice(at, 512)
                texts = []
                for html, host, ref, nodes in _rows(part, "html", "host", "reference", "nodes"):
                    found = known.get(host.as_py(), lambda: wrapper(ref, nodes)) if ref.is_valid else (None, None)  # noqa: B023
                    texts.append(apply(html.as_py(), *found))
                columns = [part.column(0), part.column(1), pa.array(texts, pa.string()), pa.array([len(t) for t in texts], pa.int64())]
                yield pa.RecordBatch.from_arrays(columns, names=["page_id", "url", "text", "n_chars"])

    return both.mapInArrow(run, "page_id long, url string, text string, n_chars long")
