"""Main-text extraction by consensus of each host's pages.

A page becomes a list of blocks, each with the generalised path of its
container (tags with their class words, digits removed). Every container is
scored by its text, less its link text; each page votes for the path of the main
container that holds its best one: the article it stands in (the whole main
element where that is its only article), else its outermost container with a class
of main content, else itself. Votes are added per host in Spark, the winning path of
every host is joined back, and the page is extracted again: all blocks anywhere
below containers on that path, whatever containers of their own they stand in.
A page without the host's path falls back to its own.

Elements that are never main text (navigation, headers, footers, asides, forms,
scripts, styles, and block elements whose class or id names adverts, notices, menus,
side bars or reader comments) are skipped wherever they stand, unless they hold the
page's first headline. Inline elements are never skipped for their class.

Defined results: null or empty html gives an empty text; a page without markup is
one block; equal votes go to the path first in order; containers deeper than a path of
``MOST_PATH`` characters count as the one around them; unclosed elements end
with their parent; an unclosed quote ends with its tag; text is whole, never cut;
a page takes time in proportion to its length; extra columns are ignored.
"""

from __future__ import annotations

import html as htmllib
import re

import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from .common import materialize, table

START = re.compile(r"<(?=[a-zA-Z!?/])")
NAME = re.compile(r"[a-zA-Z][^\s/>]*")
STOP = re.compile(r"[>=]")
QUOTE = re.compile(r"""\s*(["'])""")
#: Elements whose content is no markup, or no text of the page.
RAW = frozenset("script style textarea title noscript template xmp iframe noframes noembed svg math".split())
NAMES = re.compile(r"""(?<![\w-])(class|id|role|hidden|style)\b\s*(?:=\s*("[^"]*"|'[^']*'|[^\s"'>]+))?""", re.I)
#: Elements without content.
VOID = frozenset("area base br col embed hr img input link meta param source track wbr".split())
#: Elements that start and end a block.
BLOCK = frozenset("address article aside blockquote body caption center dd details dialog dir div dl dt fieldset figcaption figure footer form h1 h2 h3 h4 h5 h6 header hgroup hr html legend li main menu nav ol optgroup option p pre section summary table tbody td tfoot th thead tr ul".split())
#: Length from which a path takes no further steps: deeper containers count as the one they stand in.
MOST_PATH = 2000
#: Elements that are steps of a path.
CONTAINER = frozenset("article main section div td table body blockquote".split())
#: Elements that never hold main text.
SKIP = frozenset("nav header footer aside form menu dialog head select button object canvas audio video datalist".split())
#: Class and id words of blocks that are not main text.
NOISE = frozenset("ad ads adv advert adverts advertisement advertising banner sponsor sponsored promo promotion cookie cookies consent notice notices gdpr popup modal overlay menu nav navbar navigation breadcrumb breadcrumbs sidebar side aside footer header masthead comment comments respond disqus replies related recommended share sharing social newsletter subscribe signup login toolbar pager pagination widget widgets copyright legal disclaimer skip hidden".split())
CLOSES = {"p": {"p"}, "li": {"li", "p"}, "dt": {"dt", "dd", "p"}, "dd": {"dt", "dd", "p"}, "tr": {"tr", "td", "th", "p"}, "td": {"td", "th", "p"}, "th": {"td", "th", "p"}, "option": {"option"}}
SCOPE = frozenset("article section div main body table ul ol dl blockquote td th li".split())
MAIN = re.compile(r"^(article|main)\b|\.(article|content|main|post|entry|story)\b|-(body|content|text)\b")


#: First words that turn a noise word in a class or id into its absence or mention.
DENIED = frozenset("no not has have with without is hide".split())


def _noise_word(name: str) -> bool:
    """Whether one class or id names a part that is not main text."""
    parts = [w for w in re.split(r"[^a-z]+", name) if w]
    return bool(parts) and parts[0] not in DENIED and any(w in NOISE for w in parts)


def _attributes(attrs: str) -> tuple[bool, bool, str]:
    """Whether an element is hidden, and noise, by its attributes; its class words without digits."""
    classes, bad, hidden = [], False, False
    for key, value in NAMES.findall(attrs):
        key, value = key.lower(), value.strip("\"'").lower()
        if key in ("class", "id"):
            bad |= any(_noise_word(w) for w in value.split())
            if key == "class":
                classes += re.sub(r"\d+", "", value).split()
        elif key == "role":
            bad |= value in ("navigation", "banner", "contentinfo", "complementary", "search", "dialog", "menu")
        else:
            hidden |= key == "hidden" or "display:none" in value.replace(" ", "")
    return hidden, bad, ".".join(["", *sorted(set(classes))])


def tokens(page: str):
    """("text", s), ("open", tag, attributes) and ("close", tag) in page order, in time linear in the page."""
    at, n = 0, len(page)
    gone: set[str] = set()  # strings that do not occur from here on

    def find(what, start):
        if what in gone:
            return -1
        end = page.find(what, start)
        if end < 0:
            gone.add(what)
        return end

    while at < n:
        m = START.search(page, at)
        if not m:
            yield "text", page[at:]
            return
        begin = m.start()
        if begin > at:
            yield "text", page[at:begin]
        if page.startswith("<!--", begin):
            end = find("-->", begin + 4)
            at = end + 3 if end >= 0 else n
        elif page.startswith("<![CDATA[", begin):
            end = find("]]>", begin)
            yield "text", htmllib.escape(page[begin + 9 : end if end >= 0 else n])
            at = end + 3 if end >= 0 else n
        elif page[begin + 1] in "!?/":
            end = find(">", begin)
            name = NAME.match(page, begin + 2) if page[begin + 1] == "/" else None
            if end < 0 or page[begin + 1] == "/" and not name:
                yield "text", page[begin : begin + 1]
                at = begin + 1
            else:
                if name:
                    yield "close", name[0].lower()
                at = end + 1
        else:
            name = NAME.match(page, begin + 1)
            pos = name.end()
            while (stop := STOP.search(page, pos)) and stop[0] == "=":
                quote = QUOTE.match(page, stop.end())
                end = find(quote[1], quote.end()) if quote else -1
                pos = end + 1 if end >= 0 else stop.end()
            if not stop:
                yield "text", page[begin : begin + 1]
                at = begin + 1
                if find(">", at) < 0:  # no tag ends any more
                    yield "text", page[at:]
                    return
                continue
            tag, attrs, at = name[0].lower(), page[name.end() : stop.start()], stop.end()
            yield "open", tag, attrs
            if tag in RAW:
                end = find_close(page, tag, at, gone)
                at = end if end >= 0 else n
                yield "close", tag


def find_close(page: str, tag: str, at: int, gone: set) -> int:
    """The end of the next closing tag of this name, or -1."""
    key = f"</{tag}"
    if key in gone:
        return -1
    m = re.compile(rf"</{tag}\b[^>]*>", re.I).search(page, at)
    if not m:
        gone.add(key)
        return -1
    return m.end()


def first_headline(page: list) -> set[int]:
    """Tokens that open an element which holds the page's first headline."""
    open_: list[tuple[str, int]] = []
    for i, t in enumerate(page):
        if t[0] == "open":
            if t[1] == "h1":
                return {k for _, k in open_}
            if t[1] in BLOCK and t[1] not in ("p", "li", "hr"):
                open_.append((t[1], i))
        elif t[0] == "close" and t[1] in BLOCK and any(x[0] == t[1] for x in open_[-64:]):
            while open_.pop()[0] != t[1]:
                pass
    return set()


def blocks(page: str) -> list[tuple[str, str, int]]:
    """(container path, text, link characters) of the text blocks outside skipped elements, in page order."""
    out: list[tuple[str, str, int]] = []
    # tag, own path of a container (else that of the one around it), skipped, inline, stands in an article or main
    stack: list[tuple[str, str, bool, bool, bool]] = []
    text: list[str] = []
    linked = anchor = skipped = 0
    counts: dict[str, int] = {}  # open elements by tag
    parts = list(tokens(page))
    kept = first_headline(parts)

    def flush():
        nonlocal text, linked
        if text:
            joined = " ".join(htmllib.unescape("".join(text)).split())
            if joined:
                out.append((stack[-1][1] if stack else "", joined, linked))
            text, linked = [], 0

    def pop_to(depth):
        nonlocal skipped, anchor
        while len(stack) > depth:
            tag, _, skip, _, _ = stack.pop()
            counts[tag] -= 1
            skipped -= skip
            anchor -= tag == "a"

    for k, part in enumerate(parts):
        if part[0] == "text":
            if not skipped:
                text.append(part[1])
                if anchor:
                    linked += len(part[1])
            continue
        tag = part[1]
        if tag in RAW:
            continue
        if part[0] == "close":
            if tag == "br" and not skipped:
                text.append(" ")
            if not counts.get(tag):
                continue
            for i in range(len(stack) - 1, -1, -1):
                if stack[i][0] == tag:
                    if tag in BLOCK or any(not x[3] for x in stack[i:]):
                        flush()
                    pop_to(i)
                    break
                if stack[i][0] in SCOPE and tag not in BLOCK:
                    break
            continue
        if tag in VOID:
            if tag == "hr":
                flush()
            elif tag == "br" and not skipped:
                text.append(" ")
            continue
        block = tag in BLOCK
        closes = CLOSES.get(tag, ("p",))
        if block:
            flush()
            if any(counts.get(x) for x in closes):
                for i in range(len(stack) - 1, -1, -1):
                    if stack[i][0] in closes:
                        pop_to(i)
                        break
                    if stack[i][0] in SCOPE:
                        break
        if part[2].endswith("/") and not block:
            continue
        hidden, bad, classes = _attributes(part[2]) if part[2] else (False, False, "")
        inside = bool(stack) and stack[-1][4]
        bad = bad and block and tag not in ("html", "body", "main") and k not in kept
        skip = hidden and k not in kept or bad or tag in SKIP and not (tag == "header" and inside)
        above = stack[-1][1] if stack else ""
        path = f"{above}>{tag}{classes}" if tag in CONTAINER and len(above) < MOST_PATH else above
        stack.append((tag, path, skip, not block, inside or tag in ("article", "main")))
        counts[tag] = counts.get(tag, 0) + 1
        skipped += skip
        anchor += tag == "a"
    flush()
    return out


def steps(path: str) -> list[str]:
    """The path and those of the containers around it, outermost first."""
    cuts = [i for i, c in enumerate(path) if c == ">"][1:] + [len(path)]
    return [path[:i] for i in cuts] if path else [""]


def best_path(found: list[tuple[str, str, int]]) -> str | None:
    """The path of the page's main container."""
    scores: dict[str, float] = {}
    for path, text, linked in found:
        scores[path] = scores.get(path, 0.0) + max(0, len(text) - 2 * linked)
    if not scores:
        return None
    last = lambda p: p.rpartition(">")[2]
    is_main = lambda p: bool(MAIN.search(last(p)))
    best = max(sorted(scores), key=lambda p: scores[p] * (4 if is_main(p) else 1) + (1e-9 if is_main(p) else 0))
    around = steps(best)
    tag = lambda p: re.match(r"[^.]*", last(p))[0]
    article = next((p for p in reversed(around) if tag(p) == "article"), None)
    main = next((p for p in reversed(around) if tag(p) == "main"), None)
    if main is not None and (article is None or not article.startswith(f"{main}>")):
        return main
    if article is not None:
        # a headline beside the article belongs to it where main holds no other article
        others = {q for p in scores for q in steps(p) if main is not None and q.startswith(f"{main}>") and tag(q) == "article"}
        return main if main is not None and others <= set(steps(article)) else article
    return next((p for p in around if is_main(p)), best)


def extract(page: str | None, path: str | None) -> str:
    found = blocks(page or "")
    inside = lambda p, c: p == c or p.startswith(f"{c}>")
    chosen = path if path is not None and any(inside(p, path) for p, _, _ in found) else best_path(found)
    return "\n\n".join(t for p, t, _ in found if inside(p, chosen))


def page_votes(pages: DataFrame, html: str = "html", host: str = "host") -> DataFrame:
    """(host, path, votes): how many pages of the host have their best container on the path."""

    def run(batches):
        for b in batches:
            counts: dict[tuple, int] = {}
            for h, v in zip(b.column(0).to_pylist(), b.column(1), strict=True):
                path = best_path(blocks(v.as_py() or ""))
                if path is not None:
                    counts[h, path] = counts.get((h, path), 0) + 1
            rows = list(counts.items())
            yield pa.RecordBatch.from_arrays([pa.array([k[0] for k, _ in rows], pa.string()), pa.array([k[1] for k, _ in rows], pa.string()), pa.array([n for _, n in rows], pa.int64())], names=["host", "path", "votes"])

    return pages.select(F.col(host), F.col(html)).mapInArrow(run, "host string, path string, votes long").groupBy("host", "path").agg(F.sum("votes").alias("votes"))


def host_paths(pages: DataFrame) -> DataFrame:
    """(host, path): each host's winning path."""
    return page_votes(pages).groupBy("host").agg(F.min(F.struct((-F.col("votes")).alias("v"), "path"))["path"].alias("path"))


def extract_main_text(pages: DataFrame) -> DataFrame:
    """(page_id, url, text, n_chars) of all pages (page_id, url, html)."""
    host = F.coalesce(F.lower(F.regexp_extract("url", r"^[a-zA-Z][a-zA-Z0-9+.-]*://(?:[^/@]*@)?([^/:?#]*)", 1)), F.lit(""))
    rows = pages.select("page_id", "url", "html", host.alias("host"))
    # one short row per host, written first so that Spark knows its size: broadcast if small, else a join that splits hot hosts
    joined = rows.join(materialize(host_paths(rows), "host-paths"), "host", "left")

    def run(batches):
        for b in batches:
            text = [extract(v.as_py(), p) for v, p in zip(b.column(2), b.column(3).to_pylist(), strict=True)]
            yield pa.RecordBatch.from_arrays([b.column(0), b.column(1), pa.array(text, pa.string()), pa.array([len(t) for t in text], pa.int64())], names=["page_id", "url", "text", "n_chars"])

    kind = pages.schema["page_id"].dataType.simpleString()
    return joined.select("page_id", "url", "html", "path").mapInArrow(run, f"page_id {kind}, url string, text string, n_chars long")


def op4_html_main_text(spark, sf_dir) -> DataFrame:
    return extract_main_text(table(spark, sf_dir, "pages", "page_id", "url", "html"))
