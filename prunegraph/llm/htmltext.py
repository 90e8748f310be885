"""Main text of web pages by equivalence classes of template tokens.

A token is an element start with its path of tags and classes. Over the pages of a host,
tokens with the same occurrence vector (how often in which page) form a class; vectors
are compared by number of pages and a sum of per-page hashes, which partial
aggregation can add up, so no host is gathered anywhere. Classes present in most pages
make the template; classes nest below the tokens of the class that encloses them, as
their paths say. What the template leaves open are slots. The main slot is the deepest
token of a class that occurs once a page which encloses most of the text in slots, leaving
out navigation, notices, adverts, forms and the like; a page's text is that of its main
slot. A nested slot that occurs once a page and has the same text in all of ``FIXED_PAGES``
pages or more, while the main slot changes, is template too and left out, except inside
an article element: copies of an article are articles.

Defined cases: null or empty html gives empty text; a null or odd url is a host of its
own kind; a page that lacks its host's main slot uses its own article or main element,
or all that is not excluded; unclosed, misnested and cut-off markup is read as browsers
do where that matters for text; repeated rows are extracted each; empty tables give no
rows; further columns are ignored.
"""

from __future__ import annotations

import html
import re
import zlib
from collections import Counter

import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from prunegraph.llm.common import materialize

#: Names of elements with a meaning of their own.
VOID = frozenset("area base br col embed hr img input link meta param source track wbr".split())
RAW = frozenset("script style textarea title xmp noscript iframe noembed noframes template".split())
LEFT_OUT = frozenset("head nav footer aside form script style textarea title xmp noscript iframe noembed noframes template svg math button select option dialog object canvas audio video menu".split())
BLOCK = frozenset(
    "address article aside blockquote body center dd details dialog dir div dl dt fieldset figcaption figure footer form h1 h2 h3 h4 h5 h6 head header hgroup hr html legend li main menu nav ol p pre section summary table tbody td tfoot th thead title tr ul".split()
)
CLOSES_P = BLOCK - {"html", "body", "head", "title", "td", "th", "tr", "tbody", "thead", "tfoot", "legend"}
CONTAINER = frozenset("article main section div td body".split())
_SET_ASIDE = re.compile(
    r"(?:^|[\s_-])(?:ads?|advert\w*|banner|breadcrumbs?|comments?|commentlist|consent|cookies?|disqus|footer|gdpr|masthead|menu|modal|nav|navbar|navigation|newsletter|notices?|popup|promo\w*|related|replies|respond|share|sharing|sidebar|signup|site-?header|page-?header|social|sponsor\w*|subscribe|toolbar|widget)(?:$|[\s_-])",
    re.I,
)
_ROLES = re.compile(r"^(?:navigation|banner|contentinfo|complementary|search|form|dialog|alert|menu)$", re.I)
_TOKEN = re.compile(r"<!--.*?(?:-->|\Z)|<[!?][^>]*>?|</?([a-zA-Z][^\s/>]*)((?:[^>\"']|\"[^\"]*\"|'[^']*')*)>|<[/a-zA-Z][^<]*\Z", re.S)
_ATTRIBUTE = re.compile(r"\b(class|id|role|hidden|aria-hidden)\s*(?:=\s*(\"[^\"]*\"|'[^']*'|[^\s\"'>]+))?", re.I)
#: Pages that must agree before an unchanging slot counts as template.
FIXED_PAGES = 5
_SAME_CLOSES = {"li": {"ul", "ol", "menu", "dir"}, "dd": {"dl"}, "dt": {"dl"}, "tr": {"table"}, "td": {"tr", "table"}, "th": {"tr", "table"}, "option": {"select"}}


class Element:
    __slots__ = ("tag", "path", "out", "link", "article")

    def __init__(self, tag, path, out, link, article):
        self.tag, self.path, self.out, self.link, self.article = tag, path, out, link, article


def parse(page: str) -> tuple[list[tuple[str, tuple[Element, ...], int]], Counter]:
    """Blocks (text, open elements, characters inside links) in order, and the tokens."""
    stack = [Element("", "", False, False, False)]
    tokens: Counter = Counter()
    blocks, parts, linked = [], [], 0

    def flush():
        nonlocal parts, linked
        if parts:
            text = " ".join(html.unescape("".join(parts)).split())
            if text:
                blocks.append((text, tuple(stack), linked))
            parts, linked = [], 0

    def close(tag):
        for i in range(len(stack) - 1, 0, -1):
            if stack[i].tag == tag:
                del stack[i:]
                return

    at, n = 0, len(page)
    while at < n:
        m = _TOKEN.search(page, at)
        end = m.start() if m else n
        if end > at and not stack[-1].out:
            parts.append(page[at:end])
            if stack[-1].link:
                linked += end - at
        if not m:
            break
        at = m.end()
        tag = m.group(1)
        if not tag:
            continue
        tag = tag.lower()
        if page[m.start() + 1] == "/":
            if tag in BLOCK:
                flush()
                close(tag)
            elif tag == "br":
                parts.append(" ")
            elif any(e.tag == tag for e in stack):
                while stack[-1].tag != tag and stack[-1].tag not in BLOCK and len(stack) > 1:
                    stack.pop()
                if stack[-1].tag == tag:
                    stack.pop()
            continue
        if tag == "br":
            parts.append(" ")
            continue
        if tag in BLOCK:
            flush()
        if tag in CLOSES_P:
            for i in range(len(stack) - 1, 0, -1):
                if stack[i].tag == "p":
                    del stack[i:]
                    break
                if stack[i].tag in BLOCK:
                    break
        if tag in _SAME_CLOSES:
            for i in range(len(stack) - 1, 0, -1):
                if stack[i].tag == tag or (tag in ("dd", "dt") and stack[i].tag in ("dd", "dt")) or (tag in ("td", "th") and stack[i].tag in ("td", "th")):
                    del stack[i:]
                    break
                if stack[i].tag in _SAME_CLOSES[tag]:
                    break
        top = stack[-1]
        name, out = tag, top.out or tag in LEFT_OUT or (tag == "header" and not top.article)
        rest = m.group(2)
        if rest and "=" in rest or "hidden" in rest:
            for key, value in _ATTRIBUTE.findall(rest):
                key, value = key.lower(), value.strip("\"'")
                if key == "class" and value:
                    name = f"{tag}.{'.'.join(sorted(value.split()))}"
                if key in ("class", "id") and tag not in ("html", "body", "article", "main") and _SET_ASIDE.search(value):
                    out = True
                elif key == "role" and _ROLES.match(value):
                    out = True
                elif key == "hidden" or (key == "aria-hidden" and value == "true"):
                    out = True
        path = f"{top.path}/{name}"
        tokens[path] += 1
        if tag in VOID or rest.endswith("/") and tag not in BLOCK:
            continue
        if tag in RAW:
            stop = re.compile(rf"</{tag}\b[^>]*>?", re.I).search(page, at)
            at = stop.end() if stop else n
            continue
        stack.append(Element(tag, path, out, top.link or tag == "a", top.article or tag in ("article", "main")))
    flush()
    return blocks, tokens


def _host(column):
    return F.coalesce(F.lower(F.regexp_extract(column, r"^[A-Za-z][A-Za-z0-9+.-]*://([^/?#]*)", 1)), F.lit(""))


def token_rows(pages: DataFrame) -> DataFrame:
    """Per host and token, summed within a task: occurrence vector and text in its slot."""

    def run(batches):
        for batch in batches:
            sums: dict = {}
            for host, page in zip(batch.column(0).to_pylist(), batch.column(1).to_pylist()):
                blocks, tokens = parse(page or "")
                text, link, print_ = Counter(), Counter(), {}
                for words, stack, linked in blocks:
                    for e in {id(e): e for e in stack}.values():
                        text[e.path] += len(words)
                        link[e.path] += linked
                        print_[e.path] = zlib.crc32(words.encode("utf-8", "replace"), print_.get(e.path, 0))
                page_hash = zlib.crc32((page or "").encode("utf-8", "replace")) * 2654435761 % (1 << 31)
                for path, n in [*tokens.items(), ("", 1)]:
                    v = (page_hash * (2 * n + 1) + n * 40503) % (1 << 40)
                    p = print_.get(path, 0)
                    s = sums.setdefault((host, path), [0, 0, 0, 0, 0, p, p])
                    s[0] += 1
                    s[1] += v
                    s[2] = max(s[2], n)
                    s[3] += text[path]
                    s[4] += link[path]
                    s[5], s[6] = min(s[5], p), max(s[6], p)
            rows = list(zip(*((*k, *v) for k, v in sums.items())))
            if rows:
                yield pa.RecordBatch.from_arrays([pa.array(c) for c in rows], ["host", "path", "pages", "vector", "most", "chars", "link_chars", "low", "high"])

    once = pages.select(_host(F.col("url")).alias("host"), "html").mapInArrow(run, "host string, path string, pages long, vector long, most long, chars long, link_chars long, low long, high long")
    return once.groupBy("host", "path").agg(
        F.sum("pages").alias("pages"), F.sum("vector").alias("vector"), F.max("most").alias("most"), F.sum("chars").alias("chars"),
        F.sum("link_chars").alias("link_chars"), F.min("low").alias("low"), F.max("high").alias("high"),
    )


def templates(tokens: DataFrame, share: float = 0.6, often: float = 0.5) -> DataFrame:
    """host, main: the path of the main slot, fixed: slots below it that never change.
    Classes are (pages, vector) of a host."""
    all_ = tokens.filter("path = ''").select("host", F.col("pages").alias("host_pages"), F.col("chars").alias("host_chars"))
    classes = tokens.filter("path <> ''").groupBy("host", "pages", "vector").agg(F.count(F.lit(1)).alias("size"), F.max("most").alias("class_most"))
    # large and frequent: several tokens, in many pages; the root class occurs once a page
    root = classes.filter("class_most = 1 and size >= 2").join(all_, "host").filter(F.col("pages") >= often * F.col("host_pages"))
    slots = (
        tokens.join(root.select("host", "pages", "vector", "host_pages", "host_chars"), ["host", "pages", "vector"])
        .filter((F.col("low") != F.col("high")) | (F.col("pages") < 3))
        .withColumn("tag", F.regexp_extract("path", r"/([a-z0-9]+)[^/]*$", 1))
        .filter(F.col("tag").isin(*sorted(CONTAINER)))
        .filter((F.col("chars") - F.col("link_chars")) >= share * F.col("host_chars"))
        .withColumn("depth", F.size(F.split("path", "/")))
    )
    main = slots.groupBy("host").agg(F.max_by("path", F.struct("depth", "chars", "path")).alias("main"))
    nested = tokens.join(root.select("host", "pages", "vector", "host_pages"), ["host", "pages", "vector"]).join(main, "host")
    fixed = nested.filter((F.col("low") == F.col("high")) & (F.col("chars") > 0) & (F.col("pages") >= FIXED_PAGES) & F.col("path").startswith(F.concat("main", F.lit("/"))))
    fixed = fixed.filter(~F.col("path").rlike(r"/(article|main)(\.|/|$)"))
    # tokens of one template: as many as its markup has
    return main.join(fixed.groupBy("host").agg(F.collect_set("path").alias("fixed")), "host", "left")


def main_text(page: str, main: str | None, fixed: list[str] | None = None) -> str:
    blocks, _ = parse(page)
    drop = frozenset(fixed or ())
    chosen = [b for b in blocks if main and any(e.path == main for e in b[1]) and not any(e.path in drop for e in b[1])]
    if not chosen:
        chosen = [b for b in blocks if b[1][-1].article] or blocks
    return "\n\n".join(b[0] for b in chosen)


def extract(pages: DataFrame) -> DataFrame:
    """page_id, url, text, n_chars of every page."""
    found = materialize(templates(materialize(token_rows(pages), "tokens")), "templates")

    def run(batches):
        for batch in batches:
            text = [main_text(h or "", m, f) for h, m, f in zip(*(batch.column(i).to_pylist() for i in (2, 3, 4)))]
            yield pa.RecordBatch.from_arrays([batch.column(0), batch.column(1), pa.array(text, pa.string()), pa.array([len(t) for t in text], pa.int64())], ["page_id", "url", "text", "n_chars"])

    rows = pages.select(F.col("page_id").cast("long"), "url", "html", _host(F.col("url")).alias("host"))
    # a row per host: joined by its size, with skewed hosts split
    rows = rows.join(found, "host", "left").select("page_id", "url", "html", "main", "fixed")
    return rows.mapInArrow(run, "page_id long, url string, text string, n_chars long")
