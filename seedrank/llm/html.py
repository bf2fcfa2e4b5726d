"""Main text of web pages by consensus paths of their hosts.

Every page is read once to score its containers: text in blocks counts for the block's container and
half for the one around it, links count against it, and menus, notices and the like count for none.
The best container, widened to the article or main around it or to the container that holds nearly all
text, gives a generalised path (tags with their first class, digits removed): the page's vote.
Votes are summed for each host; then each page is extracted at its host's winning path, or at its own
best container where that path is absent or without text.

Defined results: a null or empty html has the empty text; a page without any scored text is extracted
at its body; a null url is a host of its own; ties go to the larger score, then the lesser path; repeated
rows give a row each; other columns are ignored.  White space is Unicode white space; a
tag that the end of the page cuts off is dropped; a page of any length is read whole, in memory in
proportion to its length.
"""

from __future__ import annotations

import re
from collections.abc import Iterator
from functools import lru_cache
from html import unescape

import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from seedrank.llm.common import named, ship, spread_join, table, written

#: Hosts up to which the table of winning paths is broadcast (some 200 bytes each).
BROADCAST_ROWS = 200_000

#: Share of a page's text outside links and marked elements that makes a container its article.
NEARLY_ALL = 0.95

#: A comment, section or declaration, or a tag with its attributes; a quote opens a value after "=" only.
_TOKEN = re.compile(
    r"<!--.*?(?:-->|\Z)|<!\[CDATA\[.*?(?:\]\]>|\Z)|<[!?][^>]*(?:>|\Z)"
    r"""|<(/?)([A-Za-z][A-Za-z0-9:-]*)((?:[^>=]+|=\s*(?:"[^"]*(?:"|\Z)|'[^']*(?:'|\Z)|[^\s>"'][^\s>]*)?)*)(>|\Z)""",
    re.DOTALL,
)
#: One attribute after the other, so that no name is looked for inside a value.
_ATTRIBUTE = re.compile(r"""([^\s=/>]+)(?:\s*=\s*(?:"([^"]*)"?|'([^']*)'?|([^\s>"'][^\s>]*)))?""")
_RAW = {"script", "style", "textarea", "title", "noscript", "template", "iframe", "xmp"}
_RAW_END = {t: re.compile(rf"</{t}\b[^>]*>?", re.IGNORECASE) for t in _RAW}
_VOID = {"area", "base", "br", "col", "embed", "hr", "img", "input", "link", "meta", "param", "source", "track", "wbr"}
#: Elements whose text is no main text.
_OUTSIDE = {"nav", "header", "footer", "aside", "form", "button", "select", "option", "datalist", "dialog", "menu", "svg", "canvas", "object", "audio", "video", "head"} | _RAW
#: Words of a class, id or role that mark such elements: whole, or as the last part of a compound.
_MARKS = set(
    "ad ads advert adverts advertisement advertising sponsor sponsors sponsored promo promos promotion banner sidebar side nav navbar navigation menu menubar footer header masthead breadcrumb breadcrumbs "
    "cookie cookies consent gdpr notice notices alert popup modal newsletter subscribe subscription share sharing social related recommended recommendations pagination pager toolbar widget widgets login signup "
    "search hidden contentinfo complementary dialog alertdialog form".split()
)
_COMMENTS = set("comment comments commentlist replies reply respond disqus".split())
#: Later parts of a compound that name no content, so that its first part decides; and first parts that negate.
_PLAIN_PARTS = set("area articles bar block body box button buttons container content field form group icons inner item items link links list main outer panel posts section slot stories text thread top unit wrap wrapper zone".split())
_NEGATIONS = {"no", "has", "with", "without", "non", "not"}
_CAMEL = re.compile(r"(?<=[a-z])(?=[A-Z])")
_PARTS = re.compile(r"[-_:.]+")
#: Share of the page's text at which a marked element with a heading or paragraphs is the article after all.
_VETO = 0.8
_BLOCK = {
    "address", "article", "blockquote", "body", "caption", "center", "dd", "details", "dir", "div", "dl", "dt", "fieldset", "figcaption", "figure", "h1", "h2", "h3", "h4", "h5", "h6",
    "hgroup", "hr", "html", "li", "main", "ol", "p", "pre", "section", "summary", "table", "tbody", "td", "tfoot", "th", "thead", "tr", "ul",
} | _OUTSIDE
#: What paths are made of; the page itself is the root, with or without tags for it.
_CONTAINER = {"article", "div", "main", "section", "td", "center", "blockquote", "details", "figure", "table"}
_ROOT = "/"
#: A start tag of the key closes an open element of the values.
_CLOSES = {"li": {"li"}, "dt": {"dt", "dd"}, "dd": {"dt", "dd"}, "tr": {"tr", "td", "th"}, "td": {"td", "th"}, "th": {"td", "th"}, "option": {"option"}}
_DIGITS = re.compile(r"\d+")


class _Mark:
    """A name that marks an element, and what stands in the element; ``around``: the next mark outside."""

    __slots__ = ("around", "comments", "chars", "blocks", "kept")

    def __init__(self, around: "_Mark | None", comments: bool):
        self.around, self.comments, self.chars, self.blocks, self.kept = around, comments, 0, 0, False


class _Element:
    __slots__ = ("tag", "path", "hard", "mark", "link")

    def __init__(self, tag: str, path: str, hard: bool, mark: _Mark | None, link: bool):
        self.tag, self.path, self.hard, self.mark, self.link = tag, path, hard, mark, link

    @property
    def outside(self) -> bool:
        """Whether the element's text is no main text."""
        mark = self.mark
        while mark is not None:
            if not mark.kept:
                return True
            mark = mark.around
        return self.hard


@lru_cache(4096)
def _marked(value: str) -> int:
    """2 if a class, id or role is that of comments, 1 if of something else beside the article, else 0."""
    found = 0
    for token in value.split():
        parts = [x for x in _PARTS.split(_DIGITS.sub("", _CAMEL.sub("-", token)).lower()) if x]
        if not parts or parts[0] in _NEGATIONS:
            continue
        for words, kind in ((_COMMENTS, 2), (_MARKS, 1)):
            if parts[-1] in words or (parts[0] in words and all(x in _PLAIN_PARTS for x in parts[1:])):
                found = max(found, kind)
    return found


def _named(tag: str, attributes: str) -> tuple[str, bool, int]:
    """The generalised name of an element, whether its text is no main text, and the mark of its names."""
    hard, mark, first = tag in _OUTSIDE, 0, ""
    if attributes and tag not in ("html", "body"):
        seen = set()
        for name, a, b, c in _ATTRIBUTE.findall(attributes):
            name = name.lower()
            if name in seen:
                continue
            seen.add(name)
            value = a or b or c
            if name == "class" and value.strip():
                first = _DIGITS.sub("", value.split()[0].lower())
            if name == "hidden" or (name == "aria-hidden" and value == "true") or (name == "style" and "display:none" in value.replace(" ", "").lower()):
                hard = True
            elif name in ("class", "id", "role") and tag not in ("article", "main"):
                mark = max(mark, _marked(value))
    return (f"{tag}.{first}" if first else tag), hard, mark


def read_page(html: str | None) -> list[tuple[str, str, _Element]]:
    """The page as ``tokens`` gives it, with the marks lifted from elements that hold nearly all of its text.

    Comments stay marked, whatever they hold.
    """
    page, total, marks = [], 0, []
    for kind, text, top in tokens(html or ""):
        page.append((kind, text, top))
        if top.mark is not None and (not marks or marks[-1] is not top.mark):
            marks.append(top.mark)
        if top.hard or (kind == "text" and top.link):
            continue
        n = len(text) - text.count(" ") if kind == "text" else 0
        total, mark = total + n, top.mark
        while mark is not None:
            mark.chars += n
            mark.blocks += 3 if kind == "break" and text in ("h1", "h2", "h3") else kind == "break" and text == "p"
            mark = mark.around
    for mark in marks:
        while mark is not None:
            mark.kept = not mark.comments and mark.blocks >= 3 and mark.chars >= _VETO * total
            mark = mark.around
    return page


def tokens(html: str) -> Iterator[tuple[str, str, _Element]]:
    """("text", its characters decoded, element), and ("break", tag of a block that begins, element) at each edge of a block."""
    stack = [_Element("", _ROOT, False, None, False)]
    at, end = 0, len(html)

    def close(depth: int) -> None:
        del stack[depth:]

    while at < end:
        m = _TOKEN.search(html, at)
        if m is None:
            tail = html[at:]
            yield "text", unescape(tail), stack[-1]
            return
        if m.start() > at:
            yield "text", unescape(html[at : m.start()]), stack[-1]
        at = m.end()
        if m[2] is None or not m[4]:  # a comment, declaration, or a tag that the page's end cuts off
            continue
        tag = m[2].lower()
        if m[1]:
            for depth in range(len(stack) - 1, 0, -1):
                if stack[depth].tag == tag:
                    if tag in _BLOCK:
                        yield "break", "", stack[-1]
                    close(depth)
                    break
            continue
        if tag in _BLOCK or tag == "br":
            yield "break", tag, stack[-1]
        if tag in _VOID:
            continue
        if tag in _BLOCK:
            # an open paragraph ends, and with it what it holds, where a block begins
            for depth in range(len(stack) - 1, 0, -1):
                if stack[depth].tag == "p":
                    close(depth)
                    break
                if stack[depth].tag in _CONTAINER or stack[depth].hard:
                    break
        for depth in range(len(stack) - 1, 0, -1) if tag in _CLOSES else ():
            if stack[depth].tag in _CLOSES[tag]:
                close(depth)
                break
            if stack[depth].tag in ("ul", "ol", "dl", "table", "select"):
                break
        name, hard, mark = _named(tag, m[3])
        top = stack[-1]
        marked = _Mark(top.mark, mark == 2) if mark else top.mark
        stack.append(_Element(tag, f"{top.path}>{name}" if tag in _CONTAINER else top.path, hard or top.hard, marked, tag == "a" or top.link))
        if m[3].endswith("/") and tag not in _RAW:
            stack.pop()
        elif tag in _RAW:
            over = _RAW_END[tag].search(html, at)
            at = over.end() if over else end
            stack.pop()


def best_path(page: list[tuple[str, str, _Element]]) -> tuple[str, float] | None:
    """Path and score of the page's best container, widened to the article around it (see ``_widened``)."""
    scores: dict[str, float] = {}
    held: dict[str, int] = {}
    for kind, text, top in page:
        if kind == "text" and not top.outside:
            n = len(" ".join(text.split()))
            if n:
                if not top.link:
                    held[top.path] = held.get(top.path, 0) + n
                n = -n if top.link else n
                scores[top.path] = scores.get(top.path, 0) + n
                around = top.path.rpartition(">")[0]
                if around:
                    scores[around] = scores.get(around, 0) + n / 2
    best = max(scores.items(), key=lambda x: (x[1], x[0]), default=None)
    return (_widened(best[0], held), best[1]) if best and best[1] > 0 else None


def _widened(path: str, held: dict[str, int]) -> str:
    """The outermost article or main that ``path`` lies in; without one, the innermost container at or
    around ``path`` that holds ``NEARLY_ALL`` of the page's text, if that is not the page itself.

    ``held``: characters of text outside links directly in each path.
    """
    steps = path.split(">")
    for i, step in enumerate(steps):
        if step.partition(".")[0] in ("article", "main"):
            return ">".join(steps[: i + 1])
    total = sum(held.values())
    for i in range(len(steps), 1, -1):
        around = ">".join(steps[:i])
        if sum(n for p, n in held.items() if p == around or p.startswith(around + ">")) >= NEARLY_ALL * total:
            return around
    return path


def text_at(page: list[tuple[str, str, _Element]], path: str | None) -> str | None:
    """Main text of the containers at ``path`` (the whole page without one); null if there are none."""
    blocks, current, seen = [], [], False
    for kind, text, top in page:
        inside = not path or top.path == path or top.path.startswith(path + ">")
        seen = seen or inside
        if kind == "break":
            blocks.append("".join(current))
            current = []
        elif inside and not top.outside:
            current.append(text)
    blocks.append("".join(current))
    return " ".join(" ".join("".join(b).split()) for b in blocks if b and not b.isspace()) if seen else None


def _host(url):
    return F.coalesce(F.regexp_extract(F.lower(url), r"^[a-z][a-z0-9+.-]*://(?:[^/@?#]*@)?([^/:?#]+)", 1), F.lit(""))


def host_paths(pages: DataFrame, url: str = "url", html: str = "html") -> DataFrame:
    """host, path, n: the path that most pages of the host vote for (null if none does), and its number of pages."""
    ship(pages.sparkSession)

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in batches:
            votes = [best_path(read_page(h.as_py())) for h in batch.column(1)]
            yield pa.RecordBatch.from_arrays(
                [batch.column(0), pa.array([v and v[0] for v in votes], pa.string()), pa.array([v and v[1] for v in votes], pa.float64())], ["host", "path", "score"]
            )

    votes = pages.select(_host(named(url)).alias("host"), named(html).alias("html")).mapInArrow(run, "host string, path string, score double")
    counted = votes.groupBy("host", "path").agg(F.count(F.lit(1)).alias("n"), F.sum("score").alias("score"))
    rank = F.when(F.col("path").isNotNull(), F.struct("n", F.round("score", 3), "path"))
    return counted.groupBy("host").agg(F.max_by("path", rank).alias("path"), F.sum("n").alias("n"))


def extract(pages: DataFrame, page_id: str = "page_id", url: str = "url", html: str = "html") -> DataFrame:
    """page_id, url and text of every page."""
    paths = written(host_paths(pages, url, html))
    rows = pages.select(named(page_id).alias("page_id"), named(url).alias("url"), _host(named(url)).alias("host"), named(html).alias("html"))
    if paths.count() <= BROADCAST_ROWS:
        rows = rows.join(F.broadcast(paths), "host", "left")
    else:  # every host is in the table; the pages of a large one are spread over tasks
        rows = spread_join(rows, paths, "host", ["page_id", "html"])
    rows = rows.select("page_id", "url", "html", "path")

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in batches:
            texts = []
            for h, p in zip(batch.column(2), batch.column(3), strict=True):
                page = read_page(h.as_py())
                found = text_at(page, p.as_py()) if p.is_valid else None
                if not found:
                    own = best_path(page)
                    found = text_at(page, own[0] if own else None)
                texts.append(found or "")
            yield pa.RecordBatch.from_arrays([batch.column(0), batch.column(1), pa.array(texts, pa.string())], ["page_id", "url", "text"])

    kind = rows.schema["page_id"].dataType.simpleString()
    return rows.mapInArrow(run, f"page_id {kind}, url string, text string")


def op7_html(spark, sf_dir: str) -> DataFrame:
    return extract(table(spark, sf_dir, "pages")).withColumn("n_chars", F.length("text").cast("long"))
