"""Main text of web pages by site template removal (op8).

A page is parsed into a tree of elements. Each block element outside paragraphs has a hash of its subtree (tag, class, text and its parts'
hashes, in one pass from the leaves up); Spark counts, for each host, on how many different pages a hash stands, and subtrees that recur
on many of them are deleted as the site's template. What is left is judged by its marks: elements whose tag, class, id or role says that they are
no article (menus, sidebars, adverts, forms, comments ...) go as well: outside articles by any word of their marks, or if they are
nearly all links; inside by tag or, for blocks that are no paragraphs, by a whole class or role. Headings, paragraphs and inline elements
never go by their marks. What is left of the article elements, or else of all outermost main elements or the body, is
the text: one line a block, white space inside a block as one space, character references decoded.

Pages that are copies of each other count once, so a copied article is no template; paragraphs and headings
inside an article are never taken for one. A hash is a template if it stands on at least `least` different pages of the host,
however many pages the host has. Every page is parsed once; those whose text holds a possible template (only their html moves) are joined with
the templates that stand in their text, so no row grows with the host, and blocks of a host are counted by block, so no host is one task.

A null page is an empty page; a null url is a host of its own (empty name); repeated rows are pages of one text each; very long and deeply nested
pages cost time in proportion. Unclosed and misnested tags are read leniently.
"""

from __future__ import annotations

import hashlib
import html
import re

import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from ruleweave.llm.common import lean, small_batches, staged

LEAST = 3
MENU_LINKS, MENU_SHARE = 3, 0.8
# Element names by role in HTML.
RAW = ("script", "style", "noscript", "template", "iframe", "object", "textarea", "title", "noembed", "noframes", "xmp")
VOID = set("area base br col embed hr img input link meta param source track wbr".split())
INLINE = set("a abbr acronym b bdi bdo big br cite code data del dfn em font i img ins kbd label mark q rp rt ruby s samp small span strike strong sub sup time tt u var wbr math mrow mi mo mn ms mtext msup msub msubsup mfrac msqrt mroot mover munder munderover mstyle mpadded mphantom mtable mtr mtd semantics merror menclose mmultiscripts mspace".split())
DROPPED = set("nav aside form script style noscript template iframe object canvas button select option input textarea menu dialog head title audio video map annotation annotation-xml".split())
DROPPED_OUTSIDE = {"header", "footer", "svg"}
HINTS = set(
    "ad ads adv advert adverts advertisement advertising adsense banner sponsor sponsored promo promotion sidebar sidebars comment comments commentlist disqus respond cookie cookies consent notice notices gdpr newsletter subscribe subscription share sharing social related recommended breadcrumb breadcrumbs menu menus nav navbar navigation pagination pager popup modal overlay widget widgets toolbar masthead complementary contentinfo alert".split()
)
REMARKS = set("comment comments commentlist disqus respond".split())
HEAD_HINTS = {"header", "footer"}
# inside an article a whole class or role counts, no part of one, and none of these, which authors give to notes of their own
INSIDE = HINTS - {"alert", "notice", "notices"}
HEADINGS = {"h1", "h2", "h3", "h4", "h5", "h6"}
TEXTUAL = HEADINGS | {"p", "pre", "blockquote", "figcaption"}
PARAGRAPHS = set("p h1 h2 h3 h4 h5 h6 pre blockquote figcaption li td th dd dt".split())
_TAG = re.compile(r"""<!--.*?(?:-->|\Z)|<[!?][^>]*>|<(/?)([a-zA-Z][^\s/>]*)((?:[^>"']++|"[^"]*+"|'[^']*+')*+)>|<(/?)([a-zA-Z][^\s/>]*)([^>]*+)>""", re.S)
_MARKS = re.compile(r"""(?<![\w-])(class|id|role)\s*=\s*(?:"([^"]*)"|'([^']*)'|([^\s>]+))""", re.I)
_WORD = re.compile(r"[a-z0-9]+")
_RAW_END = {name: re.compile(rf"</{name}(?=[\s/>]|\Z)[^>]*>?", re.I) for name in RAW}


class Node:
    __slots__ = ("tag", "marks", "kinds", "parts", "up")

    def __init__(self, tag: str, marks: str, up: Node | None, kinds: str = ""):
        self.tag, self.marks, self.kinds, self.parts, self.up = tag, marks, kinds, [], up  # kinds: the marks without ids

    def hinted(self, hints: set[str]) -> bool:
        return bool(self.marks) and not hints.isdisjoint(_WORD.findall(self.marks))

    def remark(self) -> bool:
        """A whole class, id or role says that this is a comment or holds comments."""
        return bool(self.marks) and self.tag not in ("html", "body", "main") and not REMARKS.isdisjoint(self.marks.split())

    def aside(self) -> bool:
        """A whole class or role says that this is no part of an article's text."""
        return bool(self.kinds) and not INSIDE.isdisjoint(self.kinds.split())

    def main(self) -> bool:
        return self.tag == "main" or bool(self.marks) and "main" in self.marks.split()


def parse(page: str) -> Node:
    """The tree of a page; texts among a node's parts are strings, not yet decoded."""
    root = here = Node("#root", "", None)
    at = 0
    opened: dict[str, int] = {}
    for m in iter(lambda: _TAG.search(page, at), None):
        if m.start() > at:
            here.parts.append(page[at : m.start()])
        at = m.end()
        name = (m[2] or m[5] or "").lower()
        if not name:
            continue
        if m[1] or m[4]:
            if opened.get(name):
                while here.tag != name:
                    opened[here.tag] -= 1
                    here = here.up
                opened[name] -= 1
                here = here.up
            continue
        attributes = m[3] or m[6] or ""
        if name in _RAW_END:
            end = _RAW_END[name].search(page, at)
            at = end.end() if end else len(page)
            continue
        if name not in INLINE and name not in VOID and opened.get("p"):
            here = _leave(here, opened, "p", ("table", "td", "th", "button", "object"))
        if name == "li" and opened.get("li"):
            here = _leave(here, opened, "li", ("ul", "ol", "menu"))
        elif name in ("dd", "dt") and (opened.get("dd") or opened.get("dt")):
            here = _leave(_leave(here, opened, "dd", ("dl",)), opened, "dt", ("dl",))
        elif name in ("td", "th", "tr") and opened.get("table"):
            for cell in ("td", "th") if name != "tr" else ("td", "th", "tr"):
                here = _leave(here, opened, cell, ("table",))
        found = [(kind.lower(), (a or b or c).lower()) for kind, a, b, c in _MARKS.findall(attributes)] if attributes else []
        node = Node(name, " ".join(x for _, x in found), here, " ".join(x for kind, x in found if kind != "id"))
        here.parts.append(node)
        if name not in VOID and not attributes.rstrip().endswith("/") or name in ("p", "div") and name not in VOID:
            here = node
            opened[name] = opened.get(name, 0) + 1
    if at < len(page):
        here.parts.append(page[at:])
    return root


def _leave(here: Node, opened: dict[str, int], name: str, fences: tuple[str, ...]) -> Node:
    """Closes the innermost open element of that name, unless a fence stands between."""
    if not opened.get(name):
        return here
    node = here
    while node is not None and node.tag != name:
        if node.tag in fences:
            return here
        node = node.up
    if node is None:
        return here
    while here is not node:
        opened[here.tag] -= 1
        here = here.up
    opened[name] -= 1
    return node.up


def _text(node: Node) -> str:
    """All text below a node, white space as one space."""
    out, stack = [], [node]
    while stack:
        x = stack.pop()
        if isinstance(x, str):
            out.append(x)
        else:
            stack.extend(reversed(x.parts))
            if x.tag not in INLINE or x.tag == "br":
                out.append(" ")
    return " ".join(html.unescape("".join(out)).split())


def _hash(*parts: str) -> int:
    return int.from_bytes(hashlib.blake2b("\0".join(parts).encode("utf-8", "surrogatepass"), digest_size=8).digest(), "big", signed=True)


def _walk(root: Node):
    """All nodes with whether they stand inside an article, parents first."""
    stack = [(root, False)]
    while stack:
        node, inside = stack.pop()
        yield node, inside
        inside = inside or node.tag in ("article", "main")
        stack.extend((x, inside) for x in reversed(node.parts) if not isinstance(x, str))


class Measure:
    """Of one subtree: a hash of its text and structure, characters of its text and of its links' text, links, and whether a paragraph or heading has text."""

    __slots__ = ("digest", "chars", "link_chars", "links", "prose")

    def __init__(self):
        self.digest, self.chars, self.link_chars, self.links, self.prose = b"", 0, 0, 0, False

    def menu(self) -> bool:
        """Nearly all links and no paragraph: a menu, whatever its tag is called."""
        return self.links >= MENU_LINKS and not self.prose and self.link_chars >= MENU_SHARE * self.chars


def measured(root: Node) -> dict[int, Measure]:
    """The measures of all nodes, by id, each from its parts' in one pass from the leaves up; a subtree without text has no digest."""
    out: dict[int, Measure] = {}
    stack: list[tuple[Node, bool]] = [(root, False)]
    while stack:
        node, ready = stack.pop()
        if not ready:
            stack.append((node, True))
            stack.extend((x, False) for x in node.parts if not isinstance(x, str))
            continue
        m, parts = Measure(), []
        for x in node.parts:
            if isinstance(x, str):
                text = " ".join(html.unescape(x).split())
                if text:
                    m.chars += len(text)
                    parts.append(text.encode("utf-8", "surrogatepass"))
            else:
                inner = out[id(x)]
                m.chars, m.link_chars, m.links, m.prose = m.chars + inner.chars, m.link_chars + inner.link_chars, m.links + inner.links, m.prose or inner.prose
                if inner.digest:
                    parts.append(b"\1" + inner.digest)
        if parts:
            m.digest = hashlib.blake2b(b"\0".join([f"{node.tag}\0{node.marks}".encode("utf-8", "surrogatepass"), *parts]), digest_size=8).digest()
            m.prose |= node.tag in TEXTUAL
        if node.tag == "a":
            m.link_chars, m.links = m.chars, m.links + 1
        out[id(node)] = m
    return out


def subtree_hashes(root: Node, measures: dict[int, Measure] | None = None) -> dict[int, tuple[int, Node]]:
    """Hashes of the subtrees that may be template: block elements, but no article and, inside one, no paragraph."""
    measures = measures or measured(root)
    holders: set[int] = set()
    for node, _ in _walk(root):
        if node.tag in ("article", "body", "html") or node.main():
            up = node
            while up is not None and id(up) not in holders:
                holders.add(id(up))
                up = up.up
    out = {}
    for node, inside in _walk(root):
        if id(node) in holders or node.tag in INLINE or inside and node.tag in PARAGRAPHS:
            continue
        digest = measures[id(node)].digest
        if digest:
            out[id(node)] = (int.from_bytes(digest, "big", signed=True), node)
    return out


def main_text(root: Node, templates: set[int], asked: set[int] | None = None, measures: dict[int, Measure] | None = None) -> str:
    """The article's blocks, one line each. Templates go first; what is left is judged by marks and tags. asked: gets the hashes of the blocks in
    the text that a template could delete."""
    measures = measures or measured(root)
    hashes = {key: h for key, (h, _) in subtree_hashes(root, measures).items()}
    gone = {key for key, h in hashes.items() if h in templates}
    holders: set[int] = set()
    around_main: set[int] = set()
    articles, mains, bodies = [], [], []
    for node, _ in _walk(root):
        if node.main() or node.tag == "article" and not node.remark():
            up = node.up
            while up is not None and (id(up) not in holders or node.main() and id(up) not in around_main):
                holders.add(id(up))
                if node.main():
                    around_main.add(id(up))
                up = up.up
        if node.tag == "body":
            bodies.append(node)

    def dropped(node: Node, inside: bool) -> bool:
        holder = id(node) in holders
        if id(node) in gone:
            return True
        if node.tag in DROPPED and not (node.tag == "form" and holder):
            return node.tag != "button" or node.up.tag not in HEADINGS  # a heading that unfolds its section
        if node.tag in ("html", "body", "main") or node.tag in INLINE or node.tag in TEXTUAL:
            return False
        if node.tag == "article":
            return node.remark() or node.aside()
        if id(node) in around_main or inside and node.main():
            return False
        if inside:
            return node.tag == "footer" or node.tag not in PARAGRAPHS and (node.remark() or node.aside())
        if holder:
            return node.remark()  # where each comment is an article of its own
        return node.tag in DROPPED_OUTSIDE or node.hinted(HINTS) or node.hinted(HEAD_HINTS) or measures[id(node)].menu()

    def live(start: Node):
        stack = [(start, False)]
        while stack:
            node, within = stack.pop()
            if dropped(node, within):
                continue
            yield node
            if node.tag == "article":
                articles.append(node)
                continue
            if node.main() and not within:
                mains.append(node)
            stack.extend((x, within or node.main()) for x in reversed(node.parts) if not isinstance(x, str))

    for _ in live(root):
        pass
    starts = articles or mains or bodies or [root]
    lines: list[str] = []
    buffer: list[str] = []

    def flush():
        text = " ".join(html.unescape("".join(buffer)).split())
        buffer.clear()
        if text:
            lines.append(text)

    inside = bool(articles or mains)
    for start in starts:
        stack: list = [start]
        while stack:
            x = stack.pop()
            if x is None:
                flush()
            elif isinstance(x, str):
                buffer.append(x)
            elif x is not start and dropped(x, inside):
                if x.tag not in INLINE:
                    flush()
            elif x.tag == "br":
                buffer.append(" ")
            elif x.tag in INLINE:
                stack.extend(reversed(x.parts))
            else:
                if asked is not None and x is not start and id(x) in hashes:
                    asked.add(hashes[id(x)])
                flush()
                stack.append(None)
                stack.extend(reversed(x.parts))
        flush()
    return "\n".join(lines)


def _host(url):
    return F.lower(F.coalesce(F.regexp_extract(url, r"^[A-Za-z][A-Za-z0-9+.-]*://(?:[^/?#@]*@)?([^/:?#]+)", 1), F.lit("")))


def read_pages(pages: DataFrame) -> DataFrame:
    """One row a page, each parsed once: page_id, url, host and page (hashes of the host and of the html), mark (of its text), hashes (its subtrees
    that may be template), asked (those of them that stand in its text), text (nothing deleted yet) and html (only where something is asked)."""
    small_batches(pages.sparkSession)

    def run(batches):
        for batch in batches:
            marks, hashes, wanted, texts, sources = [], [], [], [], []
            for page in batch["html"].to_pylist():
                asked: set[int] = set()
                root = parse(page or "")
                measures = measured(root)
                texts.append(main_text(root, set(), asked, measures))
                marks.append(_hash(_text(root)))
                hashes.append(sorted({h for h, _ in subtree_hashes(root, measures).values()}))
                wanted.append(sorted(asked))
                sources.append(page if asked else None)
            lists = [pa.array(x, pa.list_(pa.int64())) for x in (hashes, wanted)]
            columns = [*(batch[c] for c in ("page_id", "url", "host", "page")), pa.array(marks, pa.int64()), *lists, pa.array(texts, pa.string()), pa.array(sources, pa.string())]
            yield pa.RecordBatch.from_arrays(columns, ["page_id", "url", "host", "page", "mark", "hashes", "asked", "text", "html"])

    narrow = pages.select(F.col("page_id").cast("long").alias("page_id"), "url", F.xxhash64(_host(F.col("url"))).alias("host"), F.xxhash64("html").alias("page"), "html")
    return narrow.mapInArrow(lean(run), "page_id long, url string, host long, page long, mark long, hashes array<long>, asked array<long>, text string, html string")


def page_templates(seen: DataFrame, least: int = LEAST) -> DataFrame:
    """host, page, templates: the asked hashes of read pages that stand on `least` or more different pages of the host."""
    block = lambda hashes: F.explode(F.transform(hashes, lambda h: h.bitwiseXOR(F.col("host")))).alias("block")  # noqa: E731  a block of a host in one number
    recurring = seen.select(block("hashes"), "mark").distinct().groupBy("block").agg(F.count("*").alias("n")).filter(F.col("n") >= least).select("block")
    wanted = seen.filter(F.size("asked") > 0).select("host", "page", block("asked")).distinct()
    return wanted.join(recurring, "block", "left_semi").groupBy("host", "page").agg(F.collect_list(F.col("block").bitwiseXOR(F.col("host"))).alias("templates"))


def main_texts(pages: DataFrame, least: int = LEAST) -> DataFrame:
    """page_id, url, text, n_chars of every page."""
    seen = staged(read_pages(pages))  # read three times

    def cleaned(batches):
        for batch in batches:
            texts = []
            for page, text, templates in zip(*(batch[c].to_pylist() for c in ("html", "text", "templates")), strict=True):
                texts.append(main_text(parse(page), set(templates)) if templates else text)
            yield pa.RecordBatch.from_arrays([batch["page_id"], batch["url"], pa.array(texts, pa.string())], ["page_id", "url", "text"])

    asking = seen.filter(F.size("asked") > 0).join(page_templates(seen, least), ["host", "page"], "left").select("page_id", "url", "html", "text", "templates")
    done = seen.filter(F.size("asked") == 0).select("page_id", "url", "text")
    done = done.unionByName(asking.mapInArrow(lean(cleaned), "page_id long, url string, text string"))
    return done.withColumn("n_chars", F.length("text").cast("long"))
