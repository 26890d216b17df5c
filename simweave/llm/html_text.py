"""Main text of web pages by site template removal.

Element subtrees are hashed on every page and counted per host in Spark; subtrees that recur across many pages of a host are
its template and are deleted. Elements whose tag or role says that they are not the article go as well, and so do
those named by a class or id, unless they hold the article. Pages are read in linear time, whatever they contain.
"""

from __future__ import annotations

import html
import re
from collections.abc import Iterator

import pyarrow as pa
import xxhash
from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

from simweave.plans.staging import BROADCAST_BYTES, broadcast_if_small, fits_broadcast, stage

#: A subtree is template if it stands beside at least LEAST_PAGES different contents of its host and either a LEAST_SHARE of them
#: or MANY_PAGES.
LEAST_PAGES, LEAST_SHARE, MANY_PAGES = 5, 0.1, 50
#: Template marks of a host that travel with each of its pages; longer lists are joined mark by mark.
LIST_MARKS = 512
SALTS = 16

# Fixed lists of element names and words.
VOID = frozenset("area base br col embed hr img input link meta param source track wbr".split())
RAW = frozenset("script style textarea title noscript iframe template xmp noembed noframes".split())
DROPPED = frozenset("script style noscript template iframe nav footer aside form button select textarea input svg canvas object embed dialog menu head title label datalist audio video map".split())
BLOCK = frozenset(
    "html body article main section div p h1 h2 h3 h4 h5 h6 ul ol li dl dt dd table caption thead tbody tfoot tr blockquote pre figure figcaption header footer nav aside form fieldset address details summary hr center hgroup".split()
)
SUBTREES = frozenset("div section nav aside header footer form ul ol dl table details figure menu dialog".split())
#: Start tags that end an open paragraph.
ENDS_P = BLOCK - {"html", "body", "caption", "thead", "tbody", "tfoot", "tr"}
#: Classes of elements that a start tag ends: their members, and the elements that the search for them does not leave.
ENDED = (
    ({"p"}, {"table", "td", "th", "button", "caption", "li", "div", "article", "section", "blockquote"}), ({"li"}, {"ul", "ol", "menu"}), ({"dt", "dd"}, {"dl"}),
    ({"tr", "td", "th"}, {"table"}), ({"td", "th"}, {"tr", "table"}), ({"option"}, {"select"}), ({"thead", "tbody", "tfoot", "tr", "td", "th"}, {"table"}),
)
#: The class that a start tag ends, and what a new element changes for the elements inside it.
SIBLINGS = {"li": 1, "dt": 2, "dd": 2, "tr": 3, "td": 4, "th": 4, "option": 5, "thead": 6, "tbody": 6, "tfoot": 6}
CHANGES = {tag: [(k, tag in stops) for k, (members, stops) in enumerate(ENDED) if tag in members | stops] for tag in set().union(*(m | s for m, s in ENDED))}
ROLES = frozenset("navigation banner contentinfo complementary search form dialog alert alertdialog menu menubar toolbar".split())
#: A class or id names a part that is no article if all its words are in WORDS or FILLERS, one at least in WORDS, and the first is not in NOT.
WORDS = frozenset(
    "ad ads advert adverts advertisement advertising adsense sponsor sponsored sponsors promo promotion banner sidebar widget widgets related recommended share sharing social cookie cookies consent gdpr notice notices popup modal overlay newsletter subscribe subscription signup breadcrumb breadcrumbs pagination pager nav navbar navigation menu footer masthead topbar toolbar comment comments commentlist reply replies respond disqus login search skip".split()
)
FILLERS = frozenset(
    "a area areas b bar block body bottom box btn button buttons card cards center col column container content desktop entries entry field fixed footer form global group header heading help holder id in inline inner input item items left lg link links list main md media middle mobile module on open outer page panel post posts primary reader readers recent region right row secondary section side site size slot sm small space spot sticky story stories tab text thread title to top unit up user users view visitor wide wrap wrapper xs zone".split()
)
NOT = frozenset("no not non has have with without is hide".split())

_OPEN = re.compile(r"[a-zA-Z][^\s/>]*")
_ATTR = re.compile(r"""([^\s=/"'>]+)\s*+(?:=\s*+("[^"]*+"|'[^']*+'|[^\s"'>]+))?""")
_NAMES = re.compile(r"[A-Z]?[a-z]+|[A-Z]+|[^\W\d_]+")
_RAW_END = {tag: re.compile(rf"</{tag}(?=[\s/>])", re.I) for tag in RAW}


def tags(page: str) -> Iterator[tuple[str, str, str]]:
    """kind ('text', 'open' or 'close'), name or text, and attributes, in page order and in linear time.

    A tag ends at the first > outside quotes. Where quotes are never closed, they are ordinary characters from there on, and
    a < that nothing ends is text, like all that follows it.
    """
    at, end, quotes = 0, len(page), True
    held = 0
    while (at := page.find("<", at)) >= 0:
        lead = page[at + 1 : at + 3]
        first = lead[lead[:1] == "/" :][:1]
        if first.isascii() and first.isalpha():
            m = _OPEN.match(page, at + 1 + (lead[0] == "/"))
            stop = _tag_end(page, m.end()) if quotes else -1
            if stop < 0:
                quotes = False
                stop = page.find(">", m.end())
                if stop < 0:
                    break
            kind, name, raw = "close" if lead[0] == "/" else "open", m[0].lower(), page[m.end() : stop]
            stop += 1
        elif lead[:1] in ("!", "?", "/") and lead:
            mark = "-->" if page.startswith("<!--", at) else ">"
            stop = page.find(mark, at + 4 if len(mark) > 1 else at)
            stop = end if stop < 0 else stop + len(mark)
            kind = name = raw = ""
        else:
            at += 1
            continue
        if at > held:
            yield "text", page[held:at], ""
        at = held = stop
        if kind:
            yield kind, name, raw
        if kind == "open" and name in RAW:
            m = _RAW_END[name].search(page, at)
            close = page.find(">", m.end()) if m else -1
            at = held = end if close < 0 else close + 1
    if held < end:
        yield "text", page[held:], ""


_QUOTE_OR_END = re.compile("[>\"']")


def _tag_end(page: str, at: int) -> int:
    """Place of the > that ends a tag; -1 if the page ends inside its quotes or before."""
    while m := _QUOTE_OR_END.search(page, at):
        if m[0] == ">":
            return m.start()
        at = page.find(m[0], m.end()) + 1
        if not at:
            return -1
    return -1


def _names_part(value: str) -> bool:
    """Whether a class or id attribute names a part of a page that is no article."""
    for token in value.split():
        words = [w.lower() for w in _NAMES.findall(token)]
        if words and words[0] not in NOT and not WORDS.isdisjoint(words) and all(w in WORDS or w in FILLERS for w in words):
            return True
    return False


class Node:
    """An element: what it holds in order (texts and elements), whether it goes, whether its name says that it is no article, the
    elements that start tags inside it would end, and the hash of its subtree."""

    __slots__ = ("tag", "up", "items", "gone", "named", "heading", "main", "ends", "mark")

    def __init__(self, tag: str, up: Node | None, gone: bool, named: bool = False):
        self.tag, self.up, self.gone, self.named, self.items = tag, up, gone, named, []
        self.heading = self.main = False
        self.ends: tuple = up.ends if up else (None,) * len(ENDED)
        self.mark: xxhash.xxh64 | int = xxhash.xxh64(tag)


def _goes(tag: str, raw: str) -> tuple[bool, bool, bool]:
    """Whether an element is dropped for its tag, role or hiding, whether it is a main content element by its role, and whether a
    class or id names it as no article."""
    if not raw or "=" not in raw and "hidden" not in raw:
        return tag in DROPPED, False, False
    attrs = {}
    for m in _ATTR.finditer(raw):
        attrs.setdefault(m[1].lower(), (m[2] or "").strip("\"'"))
    role = attrs.get("role", "").lower()
    if role == "main":
        return False, True, False
    if tag in DROPPED or role in ROLES or "hidden" in attrs or attrs.get("aria-hidden") == "true" or "display:none" in attrs.get("style", "").replace(" ", "").lower():
        return True, False, False
    if tag in ("html", "body", "main", "article"):
        return False, False, False
    return False, False, _names_part(attrs.get("class", "")) or _names_part(attrs.get("id", ""))


def parse(page: str) -> tuple[Node, list[Node]]:
    """The page's element tree and its elements that can be template, in page order."""
    root = node = Node("html", None, False)
    subtrees: list[Node] = []
    open_count: dict[str, int] = {}

    def close(to: Node) -> None:
        nonlocal node
        while True:
            done = node
            node = done.up
            open_count[done.tag] -= 1
            mark = done.mark.intdigest()
            done.mark = mark
            node.mark.update(mark.to_bytes(8, "little"))
            node.heading |= done.heading or done.tag in ("h1", "h2", "h3", "h4", "h5", "h6")
            node.main |= done.main or done.tag in ("article", "main")
            if done is to:
                return

    for kind, name, raw in tags(page):
        if kind == "text":
            text = html.unescape(name)
            node.items.append(text)
            if squeezed := " ".join(text.split()):
                node.mark.update(squeezed)
            continue
        tag = name
        if kind == "close":
            if open_count.get(tag):
                x = node
                while x.tag != tag:
                    x = x.up
                close(x)
            continue
        if tag in ("html", "body"):
            continue
        if tag in ENDS_P and node.ends[0]:
            close(node.ends[0])
        if tag in SIBLINGS and node.ends[SIBLINGS[tag]]:
            close(node.ends[SIBLINGS[tag]])
        gone, main, named = _goes(tag, raw)
        child = Node(tag, node, gone, named)
        child.main = main
        node.items.append(child)
        if tag in RAW:
            child.gone, child.mark = True, 0
            continue
        if tag in VOID or raw.endswith("/") and tag not in BLOCK:
            child.mark = 0
            continue
        if tag in SUBTREES:
            subtrees.append(child)
        if tag in CHANGES:
            ends = list(child.ends)
            for k, stops in CHANGES[tag]:
                ends[k] = None if stops else ends[k] or child
            child.ends = tuple(ends)
        node = child
        open_count[tag] = open_count.get(tag, 0) + 1
    if node is not root:
        top = node
        while top.up is not root:
            top = top.up
        close(top)
    return root, subtrees


def _roots(root: Node) -> list[Node]:
    """The main content elements that stay and are not inside another one; the whole page if it has none."""
    found: dict[str, list[Node]] = {"main": [], "article": []}
    todo = [root]
    while todo:
        x = todo.pop()
        inside = [i for i in x.items if isinstance(i, Node) and (i.main or not (i.gone or i.named and i.tag != "article"))]
        for i in reversed(inside):
            if i.tag in found:
                found[i.tag].append(i)
            if i.tag != "article":
                todo.append(i)
    for tag in ("main", "article"):
        kept = [x for x in found[tag] if not x.gone]
        if kept:
            return kept
    return [root]


def _stays(x: Node, within_main: bool) -> bool:
    if x.main:
        return True
    if x.tag == "header":
        return within_main and x.heading
    return not (x.gone or x.named)


def blocks(root: Node, template: frozenset[int] = frozenset()) -> list[str]:
    """Texts of the main content's blocks in page order, white space squeezed."""
    out: list[str] = []
    held: list[str] = []

    def flush() -> None:
        text = " ".join("".join(held).split())
        if text:
            out.append(text)
        held.clear()

    for start in _roots(root):
        within = start is not root
        todo: list = [iter(start.items)]
        ends: list[bool] = [True]
        while todo:
            item = next(todo[-1], None)
            if item is None:
                todo.pop()
                if ends.pop():
                    flush()
                elif todo:
                    pass
                continue
            if isinstance(item, str):
                held.append(item)
                continue
            if not _stays(item, within) or item.tag in SUBTREES and item.mark in template and not item.main:
                if item.tag in BLOCK:
                    flush()
                continue
            if item.tag in ("br", "td", "th", "img"):
                held.append(" ")
            block = item.tag in BLOCK
            if block:
                flush()
            if item.items or block:
                todo.append(iter(item.items))
                ends.append(block)
                if item.tag in ("td", "th"):
                    held.append(" ")
        flush()
    return out


def main_text(page: str | None, template: frozenset[int] = frozenset()) -> str:
    """The article of a page, blocks joined by an empty line; empty for null or empty pages."""
    return "\n\n".join(blocks(parse(page)[0], template)) if page else ""


def host_of(url: Column) -> Column:
    """Lower-case host of a URL; empty for null or without one."""
    return F.coalesce(F.regexp_extract(F.lower(url), r"^[a-z][a-z0-9+.\-]*://(?:[^/?#@]*@)?([^/?#:]*)", 1), F.lit(""))


def _signed(mark: int) -> int:
    return mark - (1 << 64) if mark >> 63 else mark


def site_templates(pages: DataFrame, least_pages: int = LEAST_PAGES, least_share: float = LEAST_SHARE, many_pages: int = MANY_PAGES) -> DataFrame:
    """host and mark of the subtrees that are template (staged).

    A subtree counts once for each different content of its host, so that copies of one article do not make it a template.
    """

    def marks(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for b in batches:
            for lo in range(0, b.num_rows, 500):
                hosts, contents, found = [], [], []
                part = b.slice(lo, 500)
                for host, page in zip(part.column(0), part.column(1), strict=True):
                    root, subtrees = parse(page.as_py() or "")
                    content = _signed(xxhash.xxh64_intdigest("\n\n".join(blocks(root))))
                    own = {_signed(x.mark) for x in subtrees if isinstance(x.mark, int) and not x.main}
                    for mark in (0, *own):
                        hosts.append(host.as_py())
                        contents.append(content)
                        found.append(mark)
                yield pa.RecordBatch.from_arrays([pa.array(hosts, pa.string()), pa.array(contents, pa.int64()), pa.array(found, pa.int64())], ["host", "content", "mark"])

    each = pages.select(host_of(F.col("url")).alias("host"), "html").mapInArrow(marks, "host string, content long, mark long").distinct()
    counts = stage(each.groupBy("host", "mark").agg(F.count(F.lit(1)).alias("n")), "subtree-counts")
    hosts = counts.where("mark = 0").select("host", F.col("n").alias("contents"))
    often = (F.col("n") >= least_share * F.col("contents")) | (F.col("n") >= many_pages)
    found = counts.where(f"mark <> 0 and n >= {least_pages}").join(broadcast_if_small(hosts, 264), "host").where(often)
    return stage(found.select("host", "mark"), "site-templates")


def extract_pages(pages: DataFrame, id_col: str = "page_id", url_col: str = "url", html_col: str = "html", **thresholds) -> DataFrame:
    """page_id, url, text and n_chars of every page.

    Null or empty html gives an empty text; a null url belongs to the host without a name. Repeated rows are extracted each; an
    empty table gives an empty result; other columns are not read. Hosts with few template marks are joined by host, each page
    with their list; pages of other hosts are joined mark by mark with what is template, so that a page carries only marks of its own.
    """
    slim = pages.select(F.col(id_col).alias("page_id"), F.col(url_col).alias("url"), F.col(html_col).alias("html"))
    templates = site_templates(slim, **thresholds)
    keyed = slim.withColumn("host", host_of(F.col("url")))
    lengths = templates.groupBy("host").agg(F.count(F.lit(1)).alias("n"))
    long = stage(lengths.where(F.col("n") > LIST_MARKS).select("host"), "long-lists")
    short = templates.join(broadcast_if_small(long, 256), "host", "left_anti")
    lists = stage(short.groupBy("host").agg(F.collect_list("mark").alias("marks")), "template-lists")
    if fits_broadcast(short, 64, BROADCAST_BYTES):
        joined = keyed.join(F.broadcast(lists), "host", "left")
    else:
        joined = _salted(keyed, lists)
    if long.limit(1).count():
        rest = stage(keyed.join(broadcast_if_small(long, 256), "host", "left_semi").withColumn("row", F.monotonically_increasing_id()), "long-list-pages")
        joined = joined.join(broadcast_if_small(long, 256), "host", "left_anti").unionByName(_mark_by_mark(rest, templates))
    kind = slim.schema["page_id"].dataType.simpleString()

    def extract(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for b in batches:
            for lo in range(0, b.num_rows, 500):
                part = b.slice(lo, 500)
                texts = [main_text(h.as_py(), frozenset(x & (2**64 - 1) for x in m.as_py() or ())) for h, m in zip(part.column(2), part.column(3), strict=True)]
                yield pa.RecordBatch.from_arrays([part.column(0), part.column(1), pa.array(texts, pa.string()), pa.array(list(map(len, texts)), pa.int64())], ["page_id", "url", "text", "n_chars"])

    return joined.select("page_id", "url", "html", "marks").mapInArrow(extract, f"page_id {kind}, url string, text string, n_chars long")


def _salted(keyed: DataFrame, lists: DataFrame) -> DataFrame:
    """keyed pages with the list of their host (null if it has none); a hot host is spread over SALTS tasks."""
    salted = lists.withColumn("salt", F.explode(F.sequence(F.lit(0), F.lit(SALTS - 1))))
    return keyed.withColumn("salt", F.pmod(F.xxhash64("page_id"), F.lit(SALTS)).cast("int")).join(salted, ["host", "salt"], "left").drop("salt")


def _mark_by_mark(rows: DataFrame, templates: DataFrame) -> DataFrame:
    """Pages (staged, with row) with those of their own marks that are template; a hot mark is spread over SALTS tasks."""

    def marks(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for b in batches:
            for lo in range(0, b.num_rows, 500):
                part = b.slice(lo, 500)
                own = [sorted({_signed(x.mark) for x in parse(page.as_py() or "")[1] if isinstance(x.mark, int)}) for page in part.column(2)]
                yield pa.RecordBatch.from_arrays([part.column(0), part.column(1), pa.array(own, pa.list_(pa.int64()))], ["row", "host", "own"])

    each = rows.select("row", "host", "html").mapInArrow(marks, "row long, host string, own array<long>").select("row", "host", F.explode("own").alias("mark"))
    each = each.withColumn("salt", F.pmod(F.xxhash64("row"), F.lit(SALTS)).cast("int"))
    salted = templates.withColumn("salt", F.explode(F.sequence(F.lit(0), F.lit(SALTS - 1))))
    found = each.join(salted, ["host", "mark", "salt"], "left_semi").groupBy("row").agg(F.collect_list("mark").alias("marks"))
    return rows.join(found, "row", "left").drop("row")
