"""Main text of web pages, with site template removal.

A page is read once by a small tokenizer into elements and text. The subtrees of its whole body, menus and footers
included, are hashed and counted per host in Spark: a subtree that recurs on many different pages of its host is template
and is deleted. Pages count as different by their whole text, so copies of one article don't turn its own parts into
template; inside an article only containers can be template, never its paragraphs and headings. Tags, roles, classes and
ids then choose the scope, the article or main element or else the whole body, and leave out what sites with too few
pages can't show to recur: menus, forms, scripts, adverts, reader comments and the like. ``template_chars`` says how many
characters went as template, ``rule_chars`` how many by tags and classes alone.

A host's list of recurring subtrees is at most ``1 / SHARE`` times the mean number of subtrees of a page, so it is short;
it is joined to the pages by host, by broadcast only while all lists together are below a stated size.

Defined results: null or empty html gives an empty text; a null url, or one without a host, belongs to the host "";
hosts with fewer than MIN_PAGES different pages have no template; repeated rows give equal results; unclosed and
misnested elements are closed where the next block or the page ends; a tag that never ends is text; reading takes time and
memory in proportion to a page's length, whatever its nesting; other columns, whatever their names, are not read; an empty
table gives an empty result.
"""

from __future__ import annotations

import html as html_lib
import re
from bisect import bisect_right
from collections.abc import Iterator

import numpy as np
import pyarrow as pa
from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F
from pyspark.sql import types as T

from . import textkit
from .scratch import cut

MIN_PAGES = 5
SHARE = 0.05
#: Recurring subtrees, all hosts together, up to which their table is broadcast (8 bytes each).
BROADCAST_HASHES = 1_000_000

_NAME = re.compile(r"[a-zA-Z][^\s/>]*+")
_ATTRIBUTES = re.compile(r"""(?:[^>"']++|"[^"]*+"|'[^']*+')*+""")
_QUOTED = re.compile(r"""[^"']++|"[^"]*+"|'[^']*+'""")
_ATTRIBUTE = re.compile(r"""(class|id|role|hidden|aria-hidden|style)(?:\s*=\s*("[^"]*"|'[^']*'|[^\s"'>]+))?(?=[\s/]|\Z)""", re.I)

# Names of the HTML standard, and words that sites use in classes and ids.
VOID = frozenset("area base br col embed hr img input link meta param source track wbr".split())
RAW = frozenset("script style noscript template textarea title iframe svg canvas object".split())
BLOCK = frozenset(
    "address article aside blockquote body center dd details dialog div dl dt fieldset figcaption figure footer form h1 h2 h3 h4 h5 h6 header hr html li main menu nav ol p pre section summary table tbody td tfoot th thead tr ul".split()
)
LEFT_OUT = frozenset("head nav footer aside form button select menu dialog fieldset".split())
HEADINGS = frozenset("h1 h2 h3 h4 h5 h6".split())
NEVER_TEMPLATE = frozenset("html body main article p pre td th tr li dd dt h1 h2 h3 h4 h5 h6".split())
ROLES = frozenset("navigation banner contentinfo complementary search alert dialog form menu menubar toolbar".split())
WORDS = frozenset(
    "ad ads advert adverts advertisement advertising banner sponsor sponsored promo promotion cookie cookies consent gdpr notice newsletter subscribe subscription signup popup modal overlay "
    "sidebar sidebars widget widgets related recommended recommendations share sharing social breadcrumb breadcrumbs menu nav navbar navigation footer masthead topbar comment comments disqus "
    "reply replies respond pagination pager toolbar login paywall".split()
)
CLOSES_ITSELF = {"li": ("ul", "ol", "menu"), "dt": ("dl",), "dd": ("dl",), "td": ("tr", "table"), "th": ("tr", "table"), "tr": ("table",), "option": ("select",)}


def _out_of_article(tag: str, attributes: str, in_article: bool) -> bool:
    if tag in LEFT_OUT or (tag == "header" and not in_article):
        return True
    if not attributes or tag in ("html", "body", "main"):
        return False
    for m in _ATTRIBUTE.finditer(attributes):
        name, value = m[1].lower(), (m[2] or "").strip("\"'").lower()
        if name == "hidden" or (name == "aria-hidden" and value == "true") or (name == "style" and "display:none" in value.replace(" ", "")):
            return True
        if name == "role" and value in ROLES:
            return True
        if name in ("class", "id") and tag not in HEADINGS and not WORDS.isdisjoint(re.split(r"[^a-z]+", value)):
            return True
    return False


def tokens(source: str) -> Iterator[tuple[int, int, bool, str, str]]:
    """Start, end, whether it closes, name and attributes of each tag; comments and declarations have no name.

    A value ``end`` sent back moves on to there. A quote that never ends is no quote. All searches go on from where an
    earlier one ended, or are known to fail from there on, so time grows with the length.
    """
    at, quote_ends = 0, True
    failed: list[list[int]] = []  # places inside quotes, of the readings that met no end
    while (start := source.find("<", at)) >= 0:
        after = source[start + 1 : start + 2]
        name, attributes, closes = "", "", False
        if source.startswith("!--", start + 1):
            end = source.find("-->", start + 4)
            end = end + 3 if end >= 0 else len(source)
        elif after in ("!", "?"):
            end = source.find(">", start) + 1
            if not end:
                return
        else:
            closes = after == "/"
            m = _NAME.match(source, start + 1 + closes)
            if not m:
                at = start + 1
                continue
            name, end = m[0].lower(), 0
            if quote_ends and not any(_unquoted(f, m.end()) for f in failed):
                whole = _ATTRIBUTES.match(source, m.end())
                if source.startswith(">", whole.end()):
                    attributes, end = whole[0], whole.end() + 1
                elif len(failed) < 3:
                    failed.append([m.end(), *(x for q in _QUOTED.finditer(source, m.end(), whole.end()) if q[0][0] in "\"'" for x in q.span()), whole.end()])
                else:
                    quote_ends = False
            if not end:
                end = source.find(">", m.end()) + 1
                if not end:
                    return
                attributes = source[m.end() : end - 1]
        moved = yield start, end, closes, name, attributes
        if moved is not None:
            end = moved
            yield None
        at = end


def _unquoted(reading: list[int], at: int) -> bool:
    """Whether ``at`` is outside the quotes of a reading that met no end, so a reading from there meets none either."""
    return reading[0] <= at < reading[-1] and bisect_right(reading, at) % 2 == 1


class Page:
    """The blocks and subtrees of a page.

    ``blocks``: text, scope (2 inside an article, 1 inside main, else 0), innermost subtree, whether tags or classes leave it out.
    ``subtrees``: start and end in the source, scope, tag, the subtree around it, whether it is left out.
    """

    def __init__(self, source: str):
        self.source, self.blocks, self.subtrees = source, [], []
        self._read()
        self.scope = max((b[1] for b in self.blocks if not b[3]), default=0)

    def _read(self) -> None:
        source, lower = self.source, None
        stack: list[tuple[str, bool, int, int]] = []  # tag, left out, scope, innermost subtree
        places: dict[str, list[int]] = {}  # of each open tag, its places in the stack
        open_blocks: list[int] = []
        pending: tuple[list[str], list[str]] = [], []  # text that stays, and that tags and classes leave out

        def flush() -> None:
            for out in (False, True):
                if pending[out]:
                    text = " ".join("".join(pending[out]).split())
                    pending[out].clear()
                    if text:
                        _, _, scope, subtree = stack[-1] if stack else ("", False, 0, -1)
                        self.blocks.append((text, scope, subtree, out))

        def add(piece: str) -> None:
            pending[bool(stack) and stack[-1][1]].append(html_lib.unescape(piece) if "&" in piece else piece)

        def close(depth: int, end: int) -> None:
            if open_blocks and open_blocks[-1] >= depth:
                flush()
            while len(stack) > depth:
                tag, _, _, subtree = stack.pop()
                places[tag].pop()
                if open_blocks and open_blocks[-1] == len(stack):
                    open_blocks.pop()
                    if subtree >= 0 and self.subtrees[subtree][1] < 0 and self.subtrees[subtree][6] == len(stack):
                        self.subtrees[subtree][1] = end

        def last(*tags: str) -> int:
            return max((places[t][-1] for t in tags if places.get(t)), default=-1)

        at, reading = 0, tokens(source)
        for start, end, closes, tag, attributes in reading:
            if start > at:
                add(source[at:start])
            at = end
            if not tag:
                continue
            if closes:
                depth = last(tag)
                if depth >= 0 and (tag in BLOCK or not open_blocks or open_blocks[-1] < depth):
                    close(depth, at)
                elif tag in BLOCK:
                    flush()
                continue
            ends_itself = attributes.rstrip().endswith("/")
            if tag in VOID:
                if tag in ("br", "hr"):
                    add(" ")
                continue
            if tag in RAW:
                if not ends_itself:
                    lower = lower or source.lower()
                    stop = lower.find(f"</{tag}", at) if len(lower) == len(source) else -1
                    if stop < 0 and len(lower) != len(source) and (found := re.compile(f"</{tag}", re.I).search(source, at)):
                        stop = found.start()
                    if stop < 0:
                        at = len(source)
                        break
                    at = source.find(">", stop) + 1 or len(source)
                    reading.send(at)
                continue
            if tag in BLOCK:
                if tag in CLOSES_ITSELF:
                    own = ("dt", "dd") if tag in ("dt", "dd") else ("td", "th") if tag in ("td", "th") else (tag,)
                    if (depth := last(*own)) > last(*CLOSES_ITSELF[tag]):
                        close(depth, start)
                elif open_blocks and stack[open_blocks[-1]][0] == "p":
                    close(open_blocks[-1], start)
                flush()
            if ends_itself and tag not in BLOCK:
                continue
            _, out, scope, subtree = stack[-1] if stack else ("", False, 0, -1)
            out = out or _out_of_article(tag, attributes, scope == 2)
            if not out and tag in ("article", "main"):
                scope = max(scope, 2 if tag == "article" else 1)
            elif not out and "role" in attributes and re.search(r"""role\s*=\s*["']?main\b""", attributes, re.I):
                scope = max(scope, 1)
            if tag in BLOCK:
                if tag not in ("html", "body", "main", "article"):
                    self.subtrees.append([start, -1, scope, tag, subtree, out, len(stack)])
                    subtree = len(self.subtrees) - 1
                open_blocks.append(len(stack))
            places.setdefault(tag, []).append(len(stack))
            stack.append((tag, out, scope, subtree))
        if at < len(source):
            add(source[at:])
        flush()
        close(0, len(source))

    def text(self, template: frozenset[int] | set[int] = frozenset()) -> str:
        return self.parts(template)[0]

    def parts(self, template: frozenset[int] | set[int] = frozenset()) -> tuple[str, int, int]:
        """The blocks of the innermost scope that the page has, without the template's subtrees; and the characters of
        the page's blocks that went as template, and by tags and classes alone."""
        gone = [False] * len(self.subtrees)
        if template:
            for k, h in self.hashes():
                gone[k] = h in template
            for k, x in enumerate(self.subtrees):  # a subtree comes after the one around it
                gone[k] = gone[k] or (x[4] >= 0 and gone[x[4]])
        kept, by_template, by_rule = [], 0, 0
        for text, scope, subtree, out in self.blocks:
            if subtree >= 0 and gone[subtree]:
                by_template += len(text)
            elif out:
                by_rule += len(text)
            elif scope == self.scope:
                kept.append(text)
        return " ".join(kept), by_template, by_rule

    def hashes(self) -> list[tuple[int, int]]:
        """(subtree, hash of its source) of all that may be template: what tags and classes leave out, up to its outermost
        element's own blocks, and containers of the scope; each with a text inside."""
        used = [False] * len(self.subtrees)
        for _, _, subtree, _ in self.blocks:
            if subtree >= 0:
                used[subtree] = True
        for k in range(len(self.subtrees) - 1, -1, -1):
            if used[k] and self.subtrees[k][4] >= 0:
                used[self.subtrees[k][4]] = True
        picked = []
        for k, (_, _, scope, tag, around, out, _) in enumerate(self.subtrees):
            if not used[k]:
                continue
            if out:
                outer = around >= 0 and self.subtrees[around][5]
                if not outer or not (self.subtrees[around][4] >= 0 and self.subtrees[self.subtrees[around][4]][5]):
                    picked.append(k)
            elif scope == self.scope and (scope < 2 or tag not in NEVER_TEMPLATE):
                picked.append(k)
        if not picked:
            return []
        code = np.frombuffer(self.source.encode("utf-32-le", "surrogatepass"), "<u4")
        x = np.array([self.subtrees[k][:2] for k in picked], np.int64)
        return list(zip(picked, textkit.range_hashes(code, x[:, 0], x[:, 1]).view(np.int64).tolist(), strict=True))


def host_of(url: Column) -> Column:
    return F.lower(F.regexp_extract(F.coalesce(url, F.lit("")), r"^[A-Za-z][A-Za-z0-9+.\-]*://(?:[^/?#@]*@)?([^/:?#]+)", 1))


def subtree_hashes(pages: DataFrame) -> DataFrame:
    """(host, html) to (host, body, hash): a row per distinct candidate subtree of a page and one with a null hash per page."""

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        import xxhash

        for b in textkit.slices(batches, "_html"):
            host, body, hashes = [], [], []
            for h, source in zip(b.column(0).to_pylist(), b.column(1).to_pylist(), strict=True):
                page = Page(source or "")
                own = xxhash.xxh64_intdigest(page.text().encode("utf-8", "surrogatepass")) - (1 << 63)
                found = [None, *{x for _, x in page.hashes()}]
                host += [h] * len(found)
                body += [own] * len(found)
                hashes += found
            yield pa.RecordBatch.from_arrays([pa.array(host, pa.string()), pa.array(body, pa.int64()), pa.array(hashes, pa.int64())], names=["host", "body", "hash"])

    return pages.select("host", "_html").mapInArrow(run, "host string, body long, hash long")


def site_templates(pages: DataFrame, min_pages: int = MIN_PAGES, share: float = SHARE) -> DataFrame:
    """(host, html) to (host, template): the hashes of the subtrees that recur on at least ``min_pages`` and ``share`` of the host's different pages."""
    seen = subtree_hashes(pages).distinct()  # copies of a page count once
    counts = cut(seen.groupBy("host", "hash").agg(F.count("*").alias("n")).where(f"hash IS NULL OR n >= {min_pages}"))
    size = counts.where("hash IS NULL").select(F.col("host").alias("_host"), F.col("n").alias("pages"))
    often = counts.where("hash IS NOT NULL").join(size, F.col("host") == F.col("_host")).where(F.col("n") >= F.col("pages") * share)
    return often.groupBy("host").agg(F.collect_list("hash").alias("template"))


def extracted(pages: DataFrame, html: str = "html", page_id: str = "page_id", url: str = "url", min_pages: int = MIN_PAGES, share: float = SHARE) -> DataFrame:
    """page_id, url, text, n_chars, template_chars and rule_chars of each row."""
    own = pages.select(F.col(f"`{page_id}`").alias("page_id"), F.col(f"`{url}`").alias("url"), host_of(F.col(f"`{url}`")).alias("host"), F.col(f"`{html}`").alias("_html"))
    templates = cut(site_templates(own, min_pages, share)).withColumnRenamed("host", "_host")
    size = templates.agg(F.coalesce(F.sum(F.size("template")), F.lit(0)), F.count("*")).first()
    small = size[0] <= BROADCAST_HASHES and size[1] <= BROADCAST_HASHES // 8
    joined = own.join(F.broadcast(templates) if small else templates, F.col("host") == F.col("_host"), "left").select("page_id", "url", "template", "_html")
    numbers = ("n_chars", "template_chars", "rule_chars")
    schema = T.StructType([joined.schema["page_id"], joined.schema["url"], T.StructField("text", T.StringType()), *[T.StructField(n, T.LongType()) for n in numbers]])

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for b in textkit.slices(batches, "_html"):
            found = [Page(source or "").parts(frozenset(template or ())) for template, source in zip(b.column(2).to_pylist(), b.column(3).to_pylist(), strict=True)]
            texts = [f[0] for f in found]
            counts = [[len(t) for t in texts], [f[1] for f in found], [f[2] for f in found]]
            yield pa.RecordBatch.from_arrays([b.column(0), b.column(1), pa.array(texts, pa.string()), *[pa.array(c, pa.int64()) for c in counts]], names=["page_id", "url", "text", *numbers])

    return joined.mapInArrow(run, schema)
