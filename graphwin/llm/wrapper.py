"""Main text of web pages by wrapper induction.

Pages of one host come from few layouts. Each page is parsed into a tree of blocks. Trees are matched as simple tree
matching does, children in order and equal tag by equal tag: a block's place is the path of its ancestors, each by its
rank in its run of equal siblings, counted from the front or the back, so that what varies beside a block doesn't move it,
and blocks of two pages at one place are matched. Matched blocks whose text is the same are constant: the wrapper's
template. All other places are its slots, and what stands in them is the content.

A block is constant if its text stands at one place on `MIN_PAGES` unlike pages and on most pages of the layouts in which
it does; one page more is asked for where the markup speaks for content (<article>, <main>, the text of an <h1>). Pages are
unlike if one of their two longest other texts differs. Where a template would take most of a long page, the host holds near
copies of it and not a wrapper of that size: such a page is read without (`COPY_CHARS`, `COPY_SHARE`). Markup names come second:
what they rule out (navigation, headers, footers, sidebars, notices, adverts, forms, scripts, comments) is not a slot, and
if some slots lie in <article> or <main>, those are the content.

Counts merge in any order, so wrappers are learned from all pages by map-side combined aggregates and no host is gathered
in one task: one pass finds texts that recur on a host, a second one their places. Null html gives an empty text; a host
without two unlike pages has no template; repeated pages count once and are read each; extra columns are ignored.
"""

from __future__ import annotations

import hashlib
import html as html_lib
import re
from collections import Counter, defaultdict
from dataclasses import dataclass, field

import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from graphwin.session import materialize

MIN_PAGES = 2
#: Characters, and share of a page, beyond which a template is a copy of the page.
COPY_CHARS, COPY_SHARE = 400, 2 / 3
#: Recurring texts and template places (8 bytes each) are broadcast up to this many, shuffled beyond.
BROADCAST_ROWS = 1_000_000
# HTML element classes.
VOID = frozenset("area base br col embed hr img input link meta param source track wbr".split())
RAW = ("script", "style", "textarea", "title", "noscript", "template", "svg", "math", "iframe", "object", "canvas", "audio", "video")
LEFT_OUT = frozenset("script style noscript template svg math iframe object canvas audio video nav header footer aside form button select option textarea input label fieldset dialog menu head title meta link".split())
INLINE = frozenset("a abbr acronym b bdi bdo big cite code data dfn em font i ins kbd mark q ruby rb rp rt s samp small span strike strong sub sup time tt u var wbr del br img".split())
CLOSES = {"p": ("p",), "li": ("li",), "dt": ("dt", "dd"), "dd": ("dt", "dd"), "tr": ("tr", "td", "th"), "td": ("td", "th"), "th": ("td", "th"), "option": ("option",), "thead": ("tr", "td", "th"), "tbody": ("thead", "tr", "td", "th"), "tfoot": ("tbody", "tr", "td", "th")}
BLOCKS_END_P = frozenset("address article aside blockquote center details dialog dir div dl fieldset figcaption figure footer form h1 h2 h3 h4 h5 h6 header hgroup hr main menu nav ol p pre section table ul".split())
NOISE_NAMES = frozenset(
    "ad ads adv advert adverts advertisement advertising adsense sponsor sponsored promo promotion banner nav navbar navigation menu menubar topbar sidebar aside widget footer header masthead"
    " notice cookie cookies consent gdpr popup modal overlay alert newsletter subscribe subscription signup login share sharing social related recommended breadcrumb breadcrumbs pagination pager"
    " comment comments respond replies disqus reader-comments copyright disclaimer skip toolbar tagcloud".split()
)
#: Of these also a part of a name is enough ("top-menu"), on elements that hold others.
NOISE_PARTS = frozenset("ad ads advert adverts advertisement sponsored banner nav navbar navigation menu sidebar footer header masthead notice cookie cookies gdpr popup modal newsletter breadcrumb breadcrumbs pagination comment comments disqus".split())
HOLDERS = frozenset("div section ul ol dl table details figure center address".split())
NOISE_ROLES = frozenset("navigation banner contentinfo complementary search form alert dialog menu menubar toolbar".split())

# possessive: no way back into what was read, so a tag without an end costs one pass
_TOKEN = re.compile(r"<!--.*?(?:-->|$)|<!\[CDATA\[.*?(?:\]\]>|$)|<[!?][^>]*+(?:>|$)|</(?![a-zA-Z])[^>]*+(?:>|$)|<(/?)([a-zA-Z][^\s/>]*+)((?:[^>=]|=\s*+\"[^\"]*\"|=\s*+'[^']*'|=)*+)>", re.S)
_ATTR = re.compile(r"([^\s=/\"'>]+)\s*=\s*(?:\"([^\"]*)\"|'([^']*)'|([^\s\"'>]+))")
_CLASS = re.compile(r"\bclass\s*=\s*(?:\"([^\"]*)\"|'([^']*)'|([^\s\"'>]+))", re.I)
_DIGITS = re.compile(r"\d+")
_PART = re.compile(r"[^a-z0-9]+")
_RAW_END = {t: re.compile(rf"</{t}(?=[\s/>])[^>]*(?:>|$)", re.I) for t in RAW}


@dataclass
class Node:
    tag: str
    noise: bool = False
    inside: bool = False  # in <article> or <main>
    kind: str = ""  # tag and classes, without numbers
    parts: list = field(default_factory=list)  # str or Node, in page order


def _noise(tag: str, attrs: str) -> bool:
    if tag in LEFT_OUT:
        return True
    if not attrs or "=" not in attrs:
        return bool(attrs) and bool(re.search(r"(?:^|\s)hidden(?:\s|/|$)", attrs))
    if re.search(r"(?:^|\s)hidden(?:\s|/|=|$)", attrs):
        return True
    for name, a, b, c in _ATTR.findall(attrs):
        name, value = name.lower(), html_lib.unescape(a or b or c).lower()
        if name in ("class", "id"):
            for word in value.split():
                # compound names of an article or a paragraph ("post-header-1") say little; "comment" or "ad" alone does
                if word in NOISE_NAMES or tag in HOLDERS and any(p in NOISE_PARTS for p in _PART.split(word)):
                    return True
        elif name == "role" and value in NOISE_ROLES or name == "aria-hidden" and value == "true" or name == "style" and re.search(r"display\s*:\s*none", value):
            return True
    return False


def _classes(attrs: str) -> str:
    m = _CLASS.search(attrs) if attrs and "=" in attrs else None
    return _DIGITS.sub("", " ".join((m.group(1) or m.group(2) or m.group(3) or "").lower().split())) if m else ""


def parse(markup: str) -> Node:
    """The tree of a page in one pass. Text from a tag that never ends is text."""
    root = Node("#root")
    stack = [root]
    is_open: dict[str, int] = defaultdict(int)  # open elements by tag

    def cut(k: int) -> None:
        for gone in stack[k:]:
            is_open[gone.tag] -= 1
        del stack[k:]

    at, n = 0, len(markup)
    while at < n:
        lt = markup.find("<", at)
        if lt < 0:
            stack[-1].parts.append(markup[at:])
            break
        if lt > at:
            stack[-1].parts.append(markup[at:lt])
        m = _TOKEN.match(markup, lt)
        if not m:
            after = markup[lt + 1 : lt + 3].lstrip("/")[:1]
            whole = after.isascii() and after.isalpha()
            stack[-1].parts.append(markup[lt:] if whole else "<")
            at = n if whole else lt + 1
            continue
        at = m.end()
        if m.group(2) is None:
            if m.group(0).startswith("<![CDATA["):
                stack[-1].parts.append(m.group(0)[9:].removesuffix("]]>"))
            continue
        tag = m.group(2).lower()
        if m.group(1):
            if is_open[tag]:
                k = len(stack) - 1
                while stack[k].tag != tag:
                    k -= 1
                cut(k)
            continue
        if tag in CLOSES or tag in BLOCKS_END_P:
            closing = CLOSES.get(tag, ())
            if is_open["p"] and tag in BLOCKS_END_P or any(is_open[c] for c in closing):
                for k in range(len(stack) - 1, 0, -1):
                    if stack[k].tag == "p" and tag in BLOCKS_END_P or stack[k].tag in closing:
                        cut(k)
                        break
                    if stack[k].tag not in INLINE and stack[k].tag not in closing and stack[k].tag not in ("td", "th", "tr"):
                        break
        attrs = m.group(3)
        node = Node(tag, stack[-1].noise or _noise(tag, attrs) and tag not in ("html", "body"), stack[-1].inside or tag in ("article", "main"), f"{tag} {_classes(attrs)}")
        stack[-1].parts.append(node)
        if tag in RAW:
            end = _RAW_END[tag].search(markup, at)
            at = end.end() if end else n
        elif tag not in VOID:  # a slash at the end means nothing on ordinary elements
            stack.append(node)
            is_open[tag] += 1
    return root


class Place:
    """A block element among its siblings; `kids` are its own child blocks and `texts` the number of texts in it."""

    __slots__ = ("at", "kids", "kind", "marks", "parent", "ranks", "tag", "texts")

    def __init__(self, tag: str, kind: str, parent: Place | None):
        self.tag, self.kind, self.parent, self.kids, self.texts, self.ranks, self.marks = tag, kind, parent, [], 0, None, None
        if parent is not None:
            self.at = len(parent.kids)
            parent.kids.append(self)


@dataclass
class Block:
    text: str
    inside: bool
    place: Place
    nth: int


def blocks(root: Node) -> list[Block]:
    """The blocks that the markup doesn't rule out, in page order."""
    out: list[Block] = []
    now: list[str] = []

    def flush(place: Place, node: Node) -> None:
        text = " ".join(html_lib.unescape("".join(now)).split())
        now.clear()
        if text:
            out.append(Block(text, node.inside, place, place.texts))
            place.texts += 1

    top = Place("", "", None)
    todo: list = [(root, top, iter(root.parts))]
    while todo:
        node, place, rest = todo[-1]
        part = next(rest, None)
        if part is None:
            todo.pop()
            if node.tag not in INLINE and todo:
                flush(place, node)
            continue
        if isinstance(part, str):
            now.append(part)
        elif part.noise:
            if part.tag not in INLINE:
                flush(place, node)
            else:
                now.append(" ")
        elif part.tag == "br":
            now.append(" ")
        elif part.tag in INLINE:
            todo.append((part, place, iter(part.parts)))
        else:
            flush(place, node)
            todo.append((part, Place(part.tag, part.kind, place), iter(part.parts)))
    flush(top, root)
    return out


# -- alignment ---------------------------------------------------------------------------------------------------------


def _digest(*parts: bytes) -> bytes:
    return hashlib.blake2b(b"\0".join(parts), digest_size=8).digest()


def _number(digest: bytes) -> int:
    return int.from_bytes(digest, "big", signed=True)


def _bytes(number: int) -> bytes:
    return number.to_bytes(8, "big", signed=True)


def _ranks(tags: list[str]) -> list[tuple[tuple[int, int], tuple[int, int]]]:
    """Of each sibling, from the front and from the back: its run of equal tags, its rank in the run."""

    def counted(line: list[str]) -> list[tuple[int, int]]:
        out, run, n = [], -1, 0
        for i, tag in enumerate(line):
            run, n = (run, n + 1) if i and tag == line[i - 1] else (run + 1, 0)
            out.append((run, n))
        return out

    return list(zip(counted(tags), counted(tags[::-1])[::-1], strict=True))


def _marks(place: Place) -> list[bytes]:
    """The place by runs and ranks counted from the front or the back: four ways."""
    line = []
    at: Place | None = place
    while at is not None and at.marks is None:
        line.append(at)
        at = at.parent
    for p in reversed(line):
        if p.parent is None:
            p.marks = [b""] * 4
            continue
        if p.parent.ranks is None:
            p.parent.ranks = _ranks([k.tag for k in p.parent.kids])
        (run, n), (run_back, n_back) = p.parent.ranks[p.at]
        ways = ((run, n), (run, -1 - n_back), (-1 - run_back, n), (-1 - run_back, -1 - n_back))
        p.marks = [_digest(m, p.tag.encode(), b"%d %d" % w) for m, w in zip(p.parent.marks, ways, strict=True)]
    return place.marks


def _layout(found: list[Block]) -> bytes:
    """The outermost elements that stand side by side, in runs of equal ones."""
    at = found[0].place
    while at.parent is not None:
        at = at.parent
    path = []
    while len(at.kids) == 1 and not at.texts:
        at = at.kids[0]
        path.append(at.kind)
    kinds = [k.kind for i, k in enumerate(at.kids) if not i or k.kind != at.kids[i - 1].kind]
    return _digest("/".join(path).encode(), "|".join(kinds).encode())


def places(found: list[Block]) -> list[list[int]]:
    """Of each block the places it can be matched at, each with its text."""
    out = []
    for f in found:
        nth = (f.nth, f.nth - f.place.texts)
        text = f.text.encode("utf-8", "surrogatepass")
        out.append(sorted({_number(_digest(b"%d" % i, m, b"%d" % nth[i % 2], text)) for i, m in enumerate(_marks(f.place))}))
    return out


def texts(found: list[Block]) -> list[int]:
    return [_number(_digest(f.text.encode("utf-8", "surrogatepass"))) for f in found]


def evidence(found: list[Block]) -> list[tuple]:
    """(text, its places, layout, page, the two longest other texts, marked as content) of the blocks of a page."""
    own = texts(found)
    page, layout = _number(_digest(*[_bytes(t) for t in own])), _number(_layout(found))
    longest = [t for _, t in sorted({(-len(f.text), t) for f, t in zip(found, own, strict=True)})[:3]]
    heads = {f.text for f in found if f.place.tag == "h1"}
    beside = {own: _number(_digest(*[_bytes(t) for t in longest if t != own][:2])) for own in {None, *longest}}
    return [(t, at, layout, page, beside.get(t, beside[None]), f.inside or f.text in heads) for f, t, at in zip(found, own, places(found), strict=True)]


def induce(pages: list[str]) -> set[int]:
    """A host's template from pages at hand, as induce_wrappers() finds it: the reference for tests and small inputs."""
    each = [f for f in (blocks(parse(p)) for p in pages) if f]
    seen = {(mark, *e[2:]) for found in each for e in evidence(found) for mark in e[1]}
    of_layout = Counter(layout for layout, _ in {e[2:4] for found in each for e in evidence(found)})
    by_mark: dict[int, list] = defaultdict(list)
    for e in seen:
        by_mark[e[0]].append(e)
    out = set()
    for mark, rows in by_mark.items():
        enough = len(rows) >= MIN_PAGES + max(r[4] for r in rows) and 2 * len(rows) > sum(of_layout[x] for x in {r[1] for r in rows})
        if enough and len({r[3] for r in rows}) > 1:
            out.add(mark)
    return out


def main_text(markup: str | None, template: set[int] | frozenset[int] | None = None) -> str:
    """What stands in the page's slots, joined by newlines."""
    found = blocks(parse(markup)) if markup else []
    if template:
        slots = [f for f, at in zip(found, places(found), strict=True) if template.isdisjoint(at)]
        whole = sum(len(f.text) for f in found)
        taken = whole - sum(len(f.text) for f in slots)
        found = found if taken >= COPY_CHARS and taken > COPY_SHARE * whole else slots
    return "\n".join(f.text for f in ([f for f in found if f.inside] or found))


def _rows(pages: DataFrame, make, schema: pa.Schema, ddl: str) -> DataFrame:
    """make(blocks) -> rows, behind the host's number, for each page of (_host, html) that has blocks."""

    def run(batches):
        for b in batches:
            out = []
            for host, markup in zip(b.column(0).to_pylist(), b.column(1).to_pylist(), strict=True):
                found = blocks(parse(markup))
                if found:
                    out += [(host, *r) for r in make(found)]
            cols = list(zip(*out, strict=True)) or [[] for _ in schema]
            yield pa.RecordBatch.from_arrays([pa.array(c, f.type) for c, f in zip(cols, schema, strict=True)], schema=schema)

    return pages.mapInArrow(run, ddl)


def _bounded(df: DataFrame) -> DataFrame:
    """df, a written table, broadcast if it has few rows."""
    return F.broadcast(df) if df.count() <= BROADCAST_ROWS else df


def induce_wrappers(pages: DataFrame) -> DataFrame:
    """(_host, mark): the template of each host of rows (_host, html), over all its pages; written table."""
    long, flag = pa.int64(), pa.bool_()

    def named(found):
        own = texts(found)
        page, layout = _number(_digest(*[_bytes(t) for t in own])), _number(_layout(found))
        return [(0, layout, page), *((1, t, page) for t in set(own))]

    schema = pa.schema([("_host", long), ("what", pa.int32()), ("key", long), ("page", long)])
    # of layouts the pages are counted; of texts it matters only that there are two
    seen = _rows(pages, named, schema, "_host long, what int, key long, page long")
    grouped = seen.groupBy("_host", "what", "key", F.when(F.col("what") == 0, F.col("page")).alias("_page")).agg(F.min("page").alias("a"), F.max("page").alias("b"))
    grouped = materialize(grouped.where("what = 0 OR a < b"), "recurring")
    of_layout = grouped.where("what = 0").groupBy("_host", F.col("key").alias("layout")).agg(F.count("*").alias("of_layout"))
    recurring = materialize(grouped.where("what = 1").select(F.xxhash64("_host", "key").alias("_text")), "texts")

    schema = pa.schema([("_host", long), ("text", long), ("marks", pa.list_(long)), ("layout", long), ("page", long), ("beside", long), ("marked", flag)])
    where = _rows(pages, evidence, schema, "_host long, text long, marks array<long>, layout long, page long, beside long, marked boolean")
    where = where.join(_bounded(recurring), F.xxhash64("_host", "text") == F.col("_text"), "left_semi")
    where = where.select("_host", F.explode("marks").alias("mark"), "layout", "page", "beside", "marked").distinct()
    by_layout = where.groupBy("_host", "mark", "layout").agg(F.count("*").alias("agree"), F.max("marked").alias("marked"), F.min("beside").alias("a"), F.max("beside").alias("b"))
    marks = by_layout.join(of_layout, ["_host", "layout"]).groupBy("_host", "mark").agg(F.sum("agree").alias("agree"), F.sum("of_layout").alias("pages"), F.max("marked").alias("marked"), F.min("a").alias("a"), F.max("b").alias("b"))
    constant = (F.col("agree") >= MIN_PAGES + F.col("marked").cast("int")) & (2 * F.col("agree") > F.col("pages")) & (F.col("a") < F.col("b"))
    return materialize(marks.where(constant).select("_host", "mark"), "wrappers")


def extract(pages: DataFrame, id_col: str = "page_id", url_col: str = "url", html_col: str = "html") -> DataFrame:
    """page_id, url, text, n_chars of every page."""
    pages.sparkSession.conf.set("spark.sql.execution.arrow.maxRecordsPerBatch", "128")
    pages = pages.select(F.col(id_col).alias("page_id"), F.col(url_col).cast("string").alias("url"), F.col(html_col).cast("string").alias("html"))
    host = F.lower(F.regexp_extract(F.coalesce("url", F.lit("")), r"^[A-Za-z][A-Za-z0-9+.-]*://(?:[^/?#@]*@)?([^/?#:]*)", 1))
    pages = pages.withColumn("host", F.when(host != "", F.xxhash64(host)))
    marks = induce_wrappers(pages.where("host IS NOT NULL AND html IS NOT NULL").select(F.col("host").alias("_host"), "html"))
    wrappers = marks.groupBy("_host").agg(F.collect_list("mark").alias("template"))  # a host's constants, not its pages
    side = F.broadcast(wrappers) if marks.count() <= BROADCAST_ROWS else wrappers
    joined = pages.join(side, F.col("host") == F.col("_host"), "left").select("page_id", "url", "html", "template")

    def run(batches):
        for b in batches:
            out = [main_text(h, None if t is None else frozenset(t)) for h, t in zip(b.column(2).to_pylist(), b.column(3).to_pylist(), strict=True)]
            yield pa.RecordBatch.from_arrays([b.column(0), b.column(1), pa.array(out, pa.string()), pa.array([len(t) for t in out], pa.int64())], names=["page_id", "url", "text", "n_chars"])

    return joined.mapInArrow(run, f"page_id {dict(pages.dtypes)['page_id']}, url string, text string, n_chars long")
