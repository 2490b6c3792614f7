"""Main text of web pages with site template removal.

First pass: each page is parsed, and a hash of every block element's subtree (tags and
text) is emitted, beside a hash of the page's main text; Spark counts the distinct main
texts of a host whose pages hold the subtree, so copies and repeats of a page count
once. Subtrees with at least ``MIN_PAGES`` main texts and ``MIN_SHARE`` of the host's
are its template; at that share a host has at most ``1 / MIN_SHARE`` times as many as
its pages of one main text have elements, so the list by host is small. Second pass: the
list is joined by host (Spark broadcasts it only if its written size is below the
session's threshold, else it joins by shuffle, the pages of a hot host in many parts),
the page is parsed again, elements that are boilerplate by tag, role, class or state are
deleted, and the text of the main element is read without template subtrees.

Inside an element that is, or is named as, content, a class or id word that articles use
too (``share-price``, ``alert-box``) does not make boilerplate by itself: all words of
the element must be such words or neutral ones, or two of them must be, or most of its
text must be links.

Nothing inside a chosen article or main element is template, since articles may quote
each other or be near copies; an element that is only named as content often wraps the
whole page, so there only containers are template, never paragraphs or headings. Where
no text would be left, the template subtrees stay.

Defined cases: null or empty html gives empty text; a page without article or main
element gives what is left of its body; unclosed, crossed or stray tags, comments
without an end and raw ``<`` are read leniently; a null url belongs to the empty host;
equal rows give equal rows; other columns are not read.
"""

from __future__ import annotations

import html
import re

import pyarrow as pa
import xxhash
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from .common import hot_keys, materialise, salted_join, slices, table

MIN_PAGES, MIN_SHARE = 5, 0.2

_words = lambda text: frozenset(text.split())
# HTML element names by role.
VOID = _words("area base br col embed hr img input link meta param source track wbr")
RAW = _words("script style noscript template iframe svg canvas object math audio video")
BLOCKS = _words(
    "address article aside blockquote body center dd details dialog dir div dl dt fieldset figcaption figure footer form h1 h2 h3 h4 h5 h6 "
    "head header hgroup hr html legend li main menu nav ol option p pre section summary table tbody td tfoot th thead title tr ul br"
)
ENDS_P = BLOCKS - _words("br body html head title option td th tr tbody thead tfoot legend")
SELF_ENDING = {"li": ("li", "ul ol menu dir"), "dt": ("dt dd", "dl"), "dd": ("dt dd", "dl"), "tr": ("tr td th", "table tbody thead tfoot"), "td": ("td th", "tr table"), "th": ("td th", "tr table"), "option": ("option", "select")}
SELF_ENDING = {k: (_words(a), _words(b)) for k, (a, b) in SELF_ENDING.items()}
BOILERPLATE_TAGS = RAW | _words("head nav footer aside form button select input textarea dialog menu label fieldset")
BOILERPLATE_ROLES = _words("navigation banner contentinfo complementary search form dialog alertdialog alert menu menubar toolbar status note")
BOILERPLATE_WORDS = _words(
    "ad ads adv advert adverts advertisement advertising adsense sponsor sponsored promo promotion banner cookie cookies consent gdpr notice notices notification alert "
    "popup modal overlay newsletter subscribe subscription signup login sidebar aside widget widgets menu nav navbar navigation breadcrumb breadcrumbs header masthead topbar footer "
    "comment comments commentlist respond discussion disqus replies reply share sharing social related recommended recommendations toolbar pagination pager search skip hidden paywall disclaimer"
)
#: Of these words one is not enough inside the content: articles use them too.
AMBIGUOUS_WORDS = BOILERPLATE_WORDS & _words(
    "alert aside banner disclaimer discussion footer header hidden login masthead menu nav notice notices notification overlay pager pagination popup promo promotion recommendations recommended "
    "related replies reply respond search share sharing signup skip social subscription toolbar topbar widget widgets"
)
#: What may stand beside an ambiguous word in the name of boilerplate.
NEUTRAL_WORDS = _words("article bar block bottom btn button buttons container entry fixed global group icon icons inner item items left link links list main outer page post posts right row section site sticky top wrap wrapper")
#: Share of an element's text inside links at which an ambiguous word is enough.
LINK_SHARE = 0.5
MAIN_WORDS = _words("content article post entry story main body text")
PROTECTED = _words("p h1 h2 h3 h4 h5 h6 blockquote pre dd dt td th tr tbody figcaption article main body html")

TOKEN = re.compile(r"""<!--.*?(?:-->|\Z)|<[!?][^>]*>|<(/?)([A-Za-z][^\s/>]*+)((?:[^>"']|"[^"]*"|'[^']*')*+)>""", re.S)
ATTRIBUTE = re.compile(r"""([^\s=/"'>]+)(?:\s*=\s*(?:"([^"]*)"|'([^']*)'|([^\s"'>]+)))?""")
CAMEL = re.compile(r"[A-Z]?[a-z]+|[A-Z]+|\d+")


#: The end tag of an element by name; only ASCII letters are alike in both cases.
END_TAG = {tag: re.compile(f"</{tag}", re.I | re.A) for tag in RAW | {"title", "textarea"}}


class Node:
    __slots__ = ("attrs", "children", "tag")

    def __init__(self, tag: str, attrs: str = "") -> None:
        self.tag, self.attrs, self.children = tag, attrs, []


def parse(text: str) -> Node:
    """A tree of nodes and strings (references not yet decoded)."""
    root = Node("html")
    stack = [root]
    at = 0
    position = 0
    while m := TOKEN.search(text, position):
        position = m.end()
        if m.start() > at:
            stack[-1].children.append(text[at : m.start()])
        at = position
        tag = m[2]
        if tag is None:
            continue
        tag = tag.lower()
        if m[1]:
            for k in range(len(stack) - 1, 0, -1):
                if stack[k].tag == tag:
                    del stack[k:]
                    break
            continue
        if tag in RAW or tag in ("title", "textarea"):
            if m[3].endswith("/") and tag in ("svg", "math"):
                continue
            ending = END_TAG[tag].search(text, position)
            end = ending.start() if ending else len(text) if tag in ("script", "style") else position
            position = at = end
            stop = text.find(">", end)
            if ending and stop >= 0:
                position = at = stop + 1
            continue
        if tag in ENDS_P:
            for k in range(len(stack) - 1, 0, -1):
                if stack[k].tag == "p":
                    del stack[k:]
                    break
                if stack[k].tag in BLOCKS:
                    break
        if tag in SELF_ENDING:
            closes, scope = SELF_ENDING[tag]
            for k in range(len(stack) - 1, 0, -1):
                if stack[k].tag in closes:
                    del stack[k:]
                    break
                if stack[k].tag in scope:
                    break
        node = Node(tag, m[3])
        stack[-1].children.append(node)
        if tag not in VOID and not m[3].endswith("/"):
            stack.append(node)
        elif tag not in VOID and tag in BLOCKS:
            stack.append(node)
    if at < len(text):
        stack[-1].children.append(text[at:])
    return root


def attributes(raw: str) -> dict[str, str]:
    return {k.lower(): html.unescape(a or b or c) for k, a, b, c in ATTRIBUTE.findall(raw)} if raw.strip(" /") else {}


def _class_words(attrs: dict[str, str]) -> set[str]:
    return {w.lower() for w in CAMEL.findall(f"{attrs.get('class', '')} {attrs.get('id', '')}")}


def subtree_hashes(root: Node) -> dict[int, int]:
    """Hash of the subtree of each block element that holds text, by id() of the node."""
    out: dict[int, int] = {}
    done: dict[int, str] = {}
    order, stack = [], [root]
    while stack:
        node = stack.pop()
        order.append(node)
        stack.extend(c for c in node.children if isinstance(c, Node))
    for node in reversed(order):
        parts, has_text = [], False
        for c in node.children:
            if isinstance(c, Node):
                part = done[id(c)]
                has_text |= part[-1] == "1"
                parts.append(part)
            elif words := " ".join(c.split()):
                has_text = True
                parts.append(words)
        h = xxhash.xxh64_intdigest(f"{node.tag}\x00" + "\x01".join(parts))
        done[id(node)] = f"\x02{h:x}{int(has_text)}"
        if has_text and node.tag in BLOCKS:
            out[id(node)] = h - (1 << 64) if h >> 63 else h
    return out


def _has_main(node: Node) -> bool:
    stack = [node]
    while stack:
        n = stack.pop()
        for c in n.children:
            if isinstance(c, Node):
                if c.tag in ("article", "main", "h1"):
                    return True
                stack.append(c)
    return False


def _link_share(node: Node) -> float:
    """Share of an element's characters, white space aside, that are inside links."""
    total = linked = 0
    stack = [(node, False)]
    while stack:
        n, link = stack.pop()
        for c in n.children:
            if isinstance(c, Node):
                stack.append((c, link or c.tag == "a"))
            else:
                size = sum(map(len, c.split()))
                total += size
                linked += size * link
    return linked / total if total else 1.0


def _named_boilerplate(node: Node, attrs: dict[str, str], inside_content: bool) -> bool:
    words = _class_words(attrs)
    found = words & BOILERPLATE_WORDS
    if not inside_content or found - AMBIGUOUS_WORDS:
        return bool(found)
    return bool(found) and (len(found) > 1 or words <= BOILERPLATE_WORDS | NEUTRAL_WORDS or _link_share(node) >= LINK_SHARE)


def _is_boilerplate(node: Node, inside_main: bool, inside_content: bool = False) -> bool:
    if node.tag in BOILERPLATE_TAGS:
        return True
    if node.tag == "header":
        return not (inside_main or _has_main(node))
    if not node.attrs or node.tag in ("html", "body", "main"):
        return False
    attrs = attributes(node.attrs)
    if "hidden" in attrs or attrs.get("aria-hidden", "").lower() == "true" or re.search(r"display\s*:\s*none|visibility\s*:\s*hidden", attrs.get("style", ""), re.I):
        return True
    if attrs.get("role", "").lower() in BOILERPLATE_ROLES:
        return not _has_main(node)
    if _named_boilerplate(node, attrs, inside_content):
        if node.tag == "article":
            return bool(_class_words(attrs) & {"comment", "comments", "reply", "ad", "advert", "promo", "related", "sponsored"})
        return not _has_main(node)
    return False


def _is_named_content(node: Node) -> bool:
    return bool(node.attrs) and node.tag in ("div", "section", "td") and bool(_class_words(attributes(node.attrs)) & MAIN_WORDS)


def prune(root: Node, template: set[int]) -> tuple[dict[int, str], int]:
    """Delete boilerplate in place; tags of the template subtrees that are left, by id() of the node, and how many went."""
    hashes = subtree_hashes(root) if template else {}
    marked: dict[int, str] = {}
    removed = 0
    stack = [(root, False, False, False)]
    while stack:
        node, inside, content, within = stack.pop()
        kept = []
        for c in node.children:
            if isinstance(c, Node):
                main = inside or c.tag in ("article", "main")
                found = hashes.get(id(c)) in template and (c.tag not in PROTECTED or not inside and c.tag not in ("article", "main", "body", "html")) and not _has_main(c)
                if _is_boilerplate(c, inside, content):
                    removed += found and not within
                    continue
                if found:
                    marked[id(c)] = c.tag
                stack.append((c, main, main or content or _is_named_content(c), within or found))
            kept.append(c)
        node.children = kept
    return marked, removed


def text_of(root: Node, without=frozenset()) -> str:
    """White space collapsed in each block, blocks joined by a space; nodes whose id() is in ``without`` are left out."""
    parts: list[str] = []
    stack: list = [root]
    while stack:
        x = stack.pop()
        if isinstance(x, str):
            parts.append(x)
            continue
        if id(x) in without:
            continue
        if x.tag in BLOCKS:
            parts.append("\n")
            stack.append("\n")
        stack.extend(reversed(x.children))
    return " ".join(html.unescape("".join(parts)).split())


def main_element(root: Node, marked=frozenset()) -> tuple[Node, str]:
    """The article with most text beside marked nodes; else main; else an element named as content; else everything. And its kind."""
    found: dict[str, list[Node]] = {"article": [], "main": [], "named": []}
    stack = [(root, frozenset())]
    while stack:
        node, inside = stack.pop()
        for c in reversed(node.children):
            if not isinstance(c, Node):
                continue
            kind = None
            if c.tag in ("article", "main"):
                kind = c.tag
            elif c.attrs and c.tag in ("div", "section", "td"):
                attrs = attributes(c.attrs)
                kind = "main" if attrs.get("role", "").lower() == "main" else "article" if "articleBody" in attrs.get("itemprop", "") else "named" if _class_words(attrs) & MAIN_WORDS else None
            if kind and kind not in inside:
                found[kind].append(c)
            stack.append((c, inside | {kind} if kind else inside))
    for kind in ("article", "main", "named"):
        best = max(found[kind], key=lambda n: (len(text_of(n, marked)) if marked else 0, len(text_of(n))), default=None)
        if best is not None and text_of(best):
            return best, kind
    return root, "page"


def _count_marked(root: Node, main: Node, marked, without) -> int:
    """Outermost marked nodes outside the main element and outermost nodes of ``without`` inside it."""
    count, stack = 0, [(root, marked)]
    while stack:
        node, those = stack.pop()
        if node is main:
            those = without
        elif id(node) in those:
            count += 1
            continue
        stack.extend((c, those) for c in node.children if isinstance(c, Node))
    return count


def extract(page: str | None, template: set[int] = frozenset()) -> tuple[str, int]:
    """Main text, and the number of template subtrees that were deleted."""
    if not page:
        return "", 0
    root = parse(page)
    marked, removed = prune(root, template)
    main, kind = main_element(root, marked)
    without = {} if kind in ("article", "main") else {k: tag for k, tag in marked.items() if kind == "page" or tag not in PROTECTED}
    text = text_of(main, without)
    if without and not text:
        without = {}
        text = text_of(main)
    return text, removed + (_count_marked(root, main, marked, without) if marked else 0)


def with_host(pages: DataFrame, url: str = "url") -> DataFrame:
    return pages.withColumn("host", F.coalesce(F.regexp_extract(F.lower(F.col(url)), r"^[a-z][a-z0-9+.-]*://(?:[^/?#@]*@)?([^/:?#]+)", 1), F.lit("")))


def hashes_and_content(page: str | None) -> tuple[list[int], int]:
    """Distinct subtree hashes of a page, and a hash of its main text."""
    if not page:
        return [], 0
    root = parse(page)
    found = sorted(set(subtree_hashes(root).values()))
    prune(root, frozenset())
    content = xxhash.xxh64_intdigest(text_of(main_element(root)[0]))
    return found, content - (1 << 64) if content >> 63 else content


def site_templates(pages: DataFrame, min_pages: int = MIN_PAGES, min_share: float = MIN_SHARE) -> DataFrame:
    """(host, template array<long>) of pages with columns host and html; page counts are of distinct main texts."""

    def run(batches):
        for batch in slices(batches):
            found = [hashes_and_content(x) for x in batch.column(1).to_pylist()]
            yield pa.RecordBatch.from_arrays([batch.column(0), pa.array([h for h, _ in found], pa.list_(pa.int64())), pa.array([c for _, c in found], pa.int64())], names=["host", "hashes", "content"])

    hashed = pages.select("host", "html").mapInArrow(run, "host string, hashes array<long>, content long")
    # one row of hash null a page counts the host's main texts
    rows = hashed.select("host", "content", F.explode(F.concat(F.array(F.lit(None).cast("long")), "hashes")).alias("hash")).distinct()
    counts = materialise(rows.groupBy("host", "hash").agg(F.count(F.lit(1)).alias("pages")).filter(F.col("hash").isNull() | (F.col("pages") >= min_pages)))
    whole = counts.filter("hash is null").select("host", F.col("pages").alias("all"))
    frequent = counts.filter("hash is not null")
    template = salted_join(frequent, whole, "host", ["hash"], hot_keys(frequent, "host")).filter(F.col("pages") >= min_share * F.col("all"))
    return template.groupBy("host").agg(F.collect_list("hash").alias("template"))


def extract_pages(pages: DataFrame, min_pages: int = MIN_PAGES, min_share: float = MIN_SHARE) -> DataFrame:
    """Per row of pages (page_id, url, html): page_id, url, text, n_chars, n_template."""
    src = with_host(pages.select("page_id", "url", F.col("html").cast("string").alias("html")))
    templates = materialise(site_templates(src, min_pages, min_share))
    joined = salted_join(src, templates, "host", ["page_id", "url"], hot_keys(src, "host"), "left", written=True).select("page_id", "url", "html", "template")

    def run(batches):
        for batch in slices(batches):
            got = [extract(h, frozenset(t or ())) for h, t in zip(batch.column(2).to_pylist(), batch.column(3).to_pylist())]
            yield pa.RecordBatch.from_arrays(
                [batch.column(0), batch.column(1), pa.array([t for t, _ in got], pa.string()), pa.array([len(t) for t, _ in got], pa.int64()), pa.array([n for _, n in got], pa.int32())],
                names=["page_id", "url", "text", "n_chars", "n_template"],
            )

    return joined.mapInArrow(run, f"page_id {src.schema['page_id'].dataType.simpleString()}, url string, text string, n_chars long, n_template int")


def op1_page_text(spark: SparkSession, sf_dir: str) -> DataFrame:
    return extract_pages(table(spark, sf_dir, "pages"))
