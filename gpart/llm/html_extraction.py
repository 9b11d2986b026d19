"""Main text of web pages, with site templates removed.

A page is tokenised in one pass and balanced by the usual implied end tags. Every element's subtree is hashed, counted per host in
Spark, and deleted where it recurs:

- outside the content (what `article`, `main` or role=main marks, else the deepest element with more than half of the page's
  text) by its words, and by its shape: tag, role, words of class and id, and the set of its children's shapes. Headings,
  paragraphs and the like never go by their shape, nor does what holds an h1.
- inside the content by its words, unless it is plain prose (a paragraph, heading, quotation, or anything without role, class,
  id and links), so that passages which articles share stay.

An occurrence counts once for each different page content around it (outside) or for each different pair of blocks before and
after it (inside), so copies and near copies of an article never make its parts a template. A hash recurs if it has at least
`min_pages` such occurrences, and these are `min_share` of the host's different pages or `section_pages`, which catches the
templates of a section of a large host.

What never is text (scripts, styles, forms, the head) goes by its tag. What the templates leave, because it is on too few pages
of its host to be counted, goes by tag, role and words of class and id. Of a page with marked content the rest goes too. The
columns template_blocks and rule_blocks tell how many non-empty blocks the templates removed, and the rules after them.

Text between block elements forms blocks: character references are decoded, white space (also <br>) becomes one space, and
non-empty blocks are joined by two line ends. Null or empty html gives empty text; null urls share one host; extra columns are
ignored. Markup that is cut off or unbalanced never fails: open elements end with the page, and a start tag that the page's
end cuts off is no text. Every step is linear in the page's length.
"""

from __future__ import annotations

import functools
import html as entities
import re

import pyarrow as pa
import xxhash
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from gpart.llm.common import cut, of, scan, table

TEXTS = "page_id long, url string, text string, n_chars long, template_blocks long, rule_blocks long"
TAG = re.compile(r"""<(/?)([a-zA-Z][^\s/>]*)((?:"[^"]*"|'[^']*'|[^"'>])*+)""")
COMMENT_END = re.compile(r"--!?>")
ATTRIBUTE = re.compile(r"""([^\s=/"'>]+)(?:\s*=\s*("[^"]*"|'[^']*'|[^\s"'>]+))?""")
PARTS = re.compile(r"[a-z]+|[A-Z][a-z]*|\d+")
LETTERS = re.compile(r"[A-Za-z]+")

# Element classes of the HTML standard.
VOID = {"area", "base", "br", "col", "embed", "hr", "img", "input", "link", "meta", "param", "source", "track", "wbr"}
RAW = {"script", "style", "textarea", "title", "noscript", "iframe", "xmp", "noembed", "noframes"}
BLOCK = {
    "address", "article", "aside", "blockquote", "body", "caption", "center", "dd", "details", "dialog", "div", "dl", "dt", "fieldset", "figcaption", "figure", "footer", "form", "h1", "h2", "h3",
    "h4", "h5", "h6", "header", "hgroup", "hr", "html", "li", "main", "menu", "nav", "ol", "p", "pre", "section", "summary", "table", "tbody", "td", "tfoot", "th", "thead", "tr", "ul",
}
#: Elements that a start tag ends, and the elements the search for them does not leave.
ENDS = {"li": ({"li"}, {"ul", "ol", "menu"}), "dt": ({"dt", "dd"}, {"dl"}), "dd": ({"dt", "dd"}, {"dl"}), "tr": ({"tr"}, {"table"}), "td": ({"td", "th"}, {"table", "tr"}), "th": ({"td", "th"}, {"table", "tr"}), "option": ({"option"}, {"select"})}
P_ENDS = BLOCK - {"body", "html", "caption", "dd", "dt", "li", "tbody", "td", "tfoot", "th", "thead", "tr"}
P_BORDERS = {"td", "th", "button", "table", "caption", "object", "html"}
#: Never text, whatever the templates say.
NEVER = {"head", "script", "style", "noscript", "template", "form", "button", "select", "textarea", "iframe", "svg", "math", "object", "canvas", "audio", "video", "title", "datalist", "label", "input", "xmp", "noembed", "noframes"}
#: Prose: never a template by its shape, and inside the content not by its words.
PROSE = {"p", "h1", "h2", "h3", "h4", "h5", "h6", "blockquote", "pre", "article", "main", "body", "html", "dd", "dt", "li", "td", "th", "figcaption", "caption", "hgroup"}
#: For pages of hosts with too few pages to count: what is never main text by tag, by role, and by words of class and id.
BAD_TAGS = {"nav", "aside", "footer", "dialog", "menu"}
BAD_ROLES = {"navigation", "banner", "contentinfo", "complementary", "search", "dialog", "alertdialog", "alert", "menu", "menubar", "toolbar", "form"}
BAD_WORDS = set(
    "nav navbar navigation menu sidebar footer foot cookie cookies consent gdpr notice notices banner ad ads advert adverts advertisement advertising sponsor sponsored promo promoted promotion comment "
    "comments disqus reply replies respond share sharing social related recommended breadcrumb breadcrumbs newsletter subscribe subscription popup modal overlay login signup signin widget masthead toolbar pagination pager skip".split()
)
HEAD_WORDS = {"header", "masthead", "topbar"}

Event = tuple[int, str, str]
OPEN, TEXT, CLOSE = range(3)


class Stack:
    """The open elements, with the depths of each tag, so that nothing has to be searched."""

    def __init__(self):
        self.tags: list[str] = []
        self.depths: dict[str, list[int]] = {}
        self.blocks: list[int] = []

    def push(self, tag: str) -> None:
        self.depths.setdefault(tag, []).append(len(self.tags))
        if tag in BLOCK:
            self.blocks.append(len(self.tags))
        self.tags.append(tag)

    def pop(self) -> str:
        tag = self.tags.pop()
        self.depths[tag].pop()
        if tag in BLOCK:
            self.blocks.pop()
        return tag

    def last(self, tags) -> int:
        """The depth of the innermost open element of these tags, -1 if there is none."""
        return max((self.depths[t][-1] for t in tags if self.depths.get(t)), default=-1)


def events(page: str) -> list[Event]:
    """Balanced (kind, tag or text, attributes); the text of raw elements stands inside them."""
    out: list[Event] = []
    stack = Stack()
    at, end = 0, len(page)

    def close_through(depth: int) -> None:
        while len(stack.tags) > depth:
            out.append((CLOSE, stack.pop(), ""))

    def close_one_of(tags: set[str], borders: set[str]) -> None:
        if (depth := stack.last(tags)) >= 0 and depth > stack.last(borders):
            close_through(depth)

    def say(until: int) -> None:
        if until > at:
            out.append((TEXT, page[at:until], ""))

    search = 0
    while (start := page.find("<", search)) >= 0:
        found = TAG.match(page, start)
        following = "" if found else page[start + 1 : start + 3]
        if following[:1] in ("!", "?") and following:
            say(start)
            if page.startswith("<!--", start):
                close = COMMENT_END.search(page, start + 4)
                at = close.end() if close else end
            else:
                close = page.find(">", start)
                at = close + 1 if close >= 0 else end
            search = at
            continue
        if found is None:
            if following[:1] == "/" and following[1:]:  # an end tag of nothing
                say(start)
                close = page.find(">", start)
                at = search = close + 1 if close >= 0 else end
            else:
                search = start + 1
            continue
        say(start)
        until = found.end()
        if until < end and page[until] != ">":  # a quotation mark without its fellow, of which a page has one of each kind at most
            until = page.find(">", until)
        if until < 0 or until >= end:
            at = end
            break
        tag, attrs = found[2].lower(), found[3]
        at = search = until + 1
        if found[1]:
            depth = stack.last((tag,))
            if depth >= 0:
                # an end tag of a phrase does not end the block that it stands in
                if tag in BLOCK or tag in RAW or not stack.blocks or stack.blocks[-1] <= depth:
                    close_through(depth)
            elif tag == "p":
                out += [(OPEN, "p", ""), (CLOSE, "p", "")]
            continue
        if tag in P_ENDS:
            close_one_of({"p"}, P_BORDERS)
        if tag in ENDS:
            close_one_of(*ENDS[tag])
        out.append((OPEN, tag, attrs))
        if tag in VOID:
            out.append((CLOSE, tag, ""))
            continue
        stack.push(tag)
        if tag in RAW:
            stop = re.compile(rf"</{tag}(?=[\s/>])", re.IGNORECASE).search(page, at)
            until = stop.start() if stop else end
            say(until)
            at = search = until
    say(end)
    close_through(0)
    return out


def attributes(text: str) -> dict[str, str]:
    return {m[1].lower(): (m[2] or "").strip("\"'") for m in ATTRIBUTE.finditer(text)} if text.strip(" /") else {}


def boilerplate(tag: str, attrs: str, inside: bool) -> bool:
    """The rules, for what was not counted; inside: within the content, where headers belong to the article."""
    if tag in BAD_TAGS or (tag == "header" and not inside):
        return True
    if tag in ("html", "body", "main") and "role" not in attrs or "=" not in attrs and "hidden" not in attrs:
        return False
    own = attributes(attrs)
    words = {w.lower() for k in ("class", "id") for w in PARTS.findall(own.get(k, ""))}
    return "hidden" in own or own.get("role", "").lower() in BAD_ROLES or bool(words & BAD_WORDS) or (not inside and bool(words & HEAD_WORDS))


def is_main(tag: str, attrs: str) -> bool:
    return tag == "main" or ("role" in attrs and attributes(attrs).get("role", "").lower() == "main")


def marked_by(page: list[Event]) -> str | None:
    """What marks the page's content: article, main or nothing."""
    opened = [(t, a) for kind, t, a in page if kind == OPEN]
    if any(t == "article" and not boilerplate(t, a, True) for t, a in opened):
        return "article"
    return "main" if any(is_main(t, a) for t, a in opened) else None


def marks(content: str | None, tag: str, attrs: str) -> bool:
    return tag == "article" if content == "article" else is_main(tag, attrs) if content == "main" else False


def look(tag: str, attrs: str) -> str:
    """Tag, role and the words of class and id, without numbers."""
    if "=" not in attrs:
        return tag
    own = attributes(attrs)
    return "\x1f".join([tag, own.get("role", "").lower(), *(" ".join(sorted(set(LETTERS.findall(own.get(k, ""))))) for k in ("class", "id"))])


def number(*parts: str) -> int:
    return xxhash.xxh64_intdigest("\x1e".join(parts)) - (1 << 63)


@functools.lru_cache(10_000)
def shape(looks: str, below: frozenset[int]) -> int:
    return number(looks, *map(str, sorted(below)))


class Element:
    __slots__ = ("tag", "attrs", "parent", "below", "words", "shapes", "chars", "h1", "linked", "never", "marked", "first", "last", "leaf")

    def __init__(self, tag: str, attrs: str, parent: int, never: bool, marked: bool, first: int):
        self.tag, self.attrs, self.parent, self.never, self.marked, self.first = tag, attrs, parent, never, marked, first
        self.words: list[str] = []  # text and children's hashes, in order
        self.shapes: set[int] = set()
        self.chars, self.h1, self.linked, self.last, self.below, self.leaf = 0, tag == "h1", tag == "a", first, False, True

    def plain(self) -> bool:
        """Whether it never goes by its words inside the content."""
        return self.tag in PROSE or not (self.linked or self.attrs.strip(" /"))


def outline(page: list[Event]) -> tuple[list[Element], list[int], list[str]]:
    """Elements in the order of their start tags, a hash of each one's words, and the texts of the page in order."""
    content = marked_by(page)
    elements: list[Element] = []
    hashes: list[int] = []
    texts: list[str] = []
    stack: list[int] = []
    for kind, value, attrs in page:
        if kind == OPEN:
            above = elements[stack[-1]] if stack else None
            never = value in NEVER or (above is not None and above.never)
            marked = marks(content, value, attrs) or (above is not None and above.marked)
            stack.append(len(elements))
            elements.append(Element(value, attrs, stack[-2] if len(stack) > 1 else -1, never, marked, len(texts)))
            hashes.append(0)
        elif kind == TEXT:
            if (own := value.strip()) and stack and not elements[stack[-1]].never:
                here = elements[stack[-1]]
                here.words.append(own)
                here.chars += len(own)
                texts.append(own)
        else:
            at = stack.pop()
            here = elements[at]
            here.last = len(texts)
            above = elements[stack[-1]] if stack else None
            if above is not None:
                above.leaf = False
            if here.never:
                continue
            if here.marked and here.leaf and above is not None and above.marked and here.plain():
                above.words.append("\x1d".join([here.tag, *here.words]))  # needs no hash of its own
            else:
                hashes[at] = number(look(here.tag, here.attrs), *here.words)
                if above is not None and here.chars:
                    above.words.append(str(hashes[at]))
            if above is not None:
                if not here.marked:
                    above.shapes.add(shape(look(here.tag, here.attrs), frozenset(here.shapes)))
                above.chars += here.chars
                above.h1 |= here.h1
                above.linked |= here.linked
                above.below |= here.marked or here.below
    return elements, hashes, texts


def candidates(page: list[Event], host: str) -> tuple[list[tuple[int, ...]], list[tuple[int, int]], int]:
    """For each element, in the order of start tags, the hashes that would make it a template; (hash, context) pairs of the page;
    and the page's context, a hash of its content."""
    elements, hashes, texts = outline(page)
    marked = any(e.marked for e in elements)
    whole = sum(len(t) for t in texts)
    inside = [e.marked for e in elements]
    around = [e.below for e in elements]
    if not marked:
        centre = -1  # the deepest element with more than half of the text
        for at, e in enumerate(elements):
            if not e.never and 2 * e.chars > whole and e.parent == centre or (centre < 0 and 2 * e.chars > whole and not e.never):
                centre = at
        for at, e in enumerate(elements):
            inside[at] = at == centre or (e.parent >= 0 and inside[e.parent])
        while centre >= 0:
            around[centre] = True
            centre = elements[centre].parent
        context = number(*texts)
    else:
        context = number(*[str(h) for e, h in zip(elements, hashes, strict=True) if e.marked and (e.parent < 0 or not elements[e.parent].marked)])
    keys: list[tuple[int, ...]] = []
    found: list[tuple[int, int]] = []
    for at, e in enumerate(elements):
        own: list[int] = []
        if e.chars and not e.never and not (around[at] and not e.marked) and e.tag not in ("html", "body"):
            if not inside[at]:
                own.append(number(host, "words", str(hashes[at])))
                found.append((own[-1], context))
                if e.tag not in PROSE and not e.h1:
                    own.append(number(host, "shape", str(shape(look(e.tag, e.attrs), frozenset(e.shapes)))))
                    found.append((own[-1], context))
            elif not around[at] and e.parent >= 0 and inside[e.parent] and not e.plain():
                own.append(number(host, "inside", str(hashes[at])))
                found.append((own[-1], number(texts[e.first - 1] if e.first else "", texts[e.last] if e.last < len(texts) else "")))
        keys.append(tuple(own))
    return keys, found, context


KEPT, TEMPLATE, RULE, NEVER_TEXT = range(4)


def main_text(page: list[Event], keys: list[tuple[int, ...]] | None = None, drop: frozenset[int] | set[int] = frozenset(), rules: bool = True) -> tuple[str, int, int]:
    """The text and how many blocks the templates (elements with a key in drop) and the rules removed."""
    content = marked_by(page)
    blocks: list[str] = []
    held: dict[int, list[str]] = {KEPT: [], TEMPLATE: [], RULE: []}
    removed = {TEMPLATE: 0, RULE: 0}
    stack: list[tuple[int, bool]] = []  # why it goes, whether it is content
    at = 0

    def end_block() -> None:
        for why, parts in held.items():
            if parts:
                text = " ".join(entities.unescape("".join(parts)).split())
                if text and why == KEPT:
                    blocks.append(text)
                elif text:
                    removed[why] += 1
                parts.clear()

    for kind, value, attrs in page:
        if kind == TEXT:
            why, inside = stack[-1] if stack else (KEPT, False)
            if why == KEPT and rules and content and not inside:
                why = RULE
            if why != NEVER_TEXT:
                held[why].append(value)
            continue
        if value in BLOCK:
            end_block()
        elif value == "br":
            for parts in held.values():
                parts.append(" ")
        if kind == OPEN:
            why, inside = stack[-1] if stack else (KEPT, False)
            inside = inside or marks(content, value, attrs)
            if value in NEVER:
                why = NEVER_TEXT
            elif why == KEPT and drop and any(k in drop for k in keys[at]):
                why = TEMPLATE
            elif why == KEPT and rules and boilerplate(value, attrs, inside):
                why = RULE
            stack.append((why, inside))
            at += 1
        else:
            stack.pop()
    end_block()
    return "\n\n".join(blocks), removed[TEMPLATE], removed[RULE]


def host_of(url: str | None) -> str:
    rest = (url or "").partition("//")[2] or (url or "")
    return re.split(r"[/?#]", rest, maxsplit=1)[0].lower()


def recurring(pages: DataFrame, min_pages: int, min_share: float, section_pages: int) -> DataFrame:
    """hash of the subtrees that recur on many different pages of their host."""

    def rows(batch: pa.RecordBatch) -> dict[str, list]:
        out: dict[str, list] = {"host": [], "hash": [], "context": []}
        for url, page in zip(batch.column("url").to_pylist(), batch.column("html").to_pylist(), strict=True):
            host = host_of(url)
            own = number(host)
            _, found, context = candidates(events(page or ""), host)
            for key, around in {(own, context), *found}:  # the host's own number stands for its pages
                out["host"].append(own), out["hash"].append(key), out["context"].append(around)
        return out

    found = scan(pages.select("url", "html"), rows, "host long, hash long, context long").distinct()
    counts = found.groupBy("host", "hash").count().where(F.col("count") >= min_pages)
    size = counts.where(F.col("host") == F.col("hash")).select("host", F.col("count").alias("pages"))
    many = (F.col("count") >= min_share * F.col("pages")) | (F.col("count") >= section_pages)
    return counts.where(F.col("host") != F.col("hash")).join(size, "host").where(many).select("hash")


def extract(
    pages: DataFrame, *, id_col: str = "page_id", url_col: str = "url", html_col: str = "html",
    min_pages: int = 5, min_share: float = 0.3, section_pages: int = 100, most_broadcast: int = 200_000, rules: bool = True,
) -> DataFrame:
    """The columns of TEXTS for every page. The recurring hashes are broadcast if they are at most most_broadcast, else they are
    joined to their pages. rules=False leaves everything to the templates, but for what never is text."""
    own = of(pages, page_id=id_col, url=url_col, html=html_col)
    spark = own.sparkSession
    found = cut(recurring(own, min_pages, min_share, section_pages))
    first = [r["hash"] for r in found.limit(most_broadcast + 1).collect()]

    def text_of(url: str | None, page: str | None, drop) -> tuple[str, int, int]:
        if not page:
            return "", 0, 0
        parts = events(page)
        return main_text(parts, candidates(parts, host_of(url))[0] if drop else None, drop, rules)

    def rows_with(drops):
        def rows(batch: pa.RecordBatch) -> dict[str, list]:
            urls = batch.column("url").to_pylist()
            texts = [text_of(url, page, drop) for url, page, drop in zip(urls, batch.column("html").to_pylist(), drops(batch), strict=True)]
            return {"page_id": batch.column("page_id"), "url": urls, "text": [t for t, _, _ in texts], "n_chars": [len(t) for t, _, _ in texts], "template_blocks": [n for _, n, _ in texts], "rule_blocks": [n for _, _, n in texts]}

        return rows

    if len(first) <= most_broadcast:
        held = spark.sparkContext.broadcast(frozenset(first))
        return scan(own, rows_with(lambda batch: [held.value] * batch.num_rows), TEXTS)

    def keyed_hashes(batch: pa.RecordBatch) -> dict[str, list]:
        got = [(k, h) for k, url, page in zip(*(batch.column(c).to_pylist() for c in ("key", "url", "html")), strict=True) if page for h in {x for xs in candidates(events(page), host_of(url))[0] for x in xs}]
        return {"key": [k for k, _ in got], "hash": [h for _, h in got]}

    keyed = own.withColumn("key", F.sha2(F.concat_ws("\x1f", "url", "html"), 256))
    drops = scan(keyed.select("key", "url", "html"), keyed_hashes, "key string, hash long").distinct().join(found, "hash").groupBy("key").agg(F.collect_list("hash").alias("drop"))  # at most a page's elements
    return scan(keyed.join(drops, "key", "left").drop("key"), rows_with(lambda batch: [set(d or ()) for d in batch.column("drop").to_pylist()]), TEXTS)


def op5_html_extraction(spark: SparkSession, sf_dir: str) -> DataFrame:
    return extract(table(spark, sf_dir, "pages"))
