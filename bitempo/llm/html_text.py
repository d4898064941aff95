"""Main text of web pages by deducing each host's template from equivalence classes of tokens.

Tokens are containers with their path from the root (tag and class names) and blocks of text with theirs. Tokens that occur equally often
in every page of a host share an occurrence vector and form a class. A class is valid if at least half of the host's pages, and two, hold
it (three for text in an article, since two pages may be versions of one text), and if it holds a container or three words. Valid classes
nest by their containers' paths and make the host's template; the text under it that no valid class covers fills its slots, in
articles as elsewhere. Among slots, those in navigation, headers, footers, sidebars, notices, adverts, forms and reader comments, whose
text may differ from page to page, are known by their containers; of the rest the article's slots are the main text, or all
slots if none is in an article. A page that has no slot of its own is read by containers alone.

Pages of equal text count once: copies are no evidence of a template. Occurrence vectors are compared by two aggregates that combine
in any order (pages held, and an exclusive or of a hash of page and count), so pages of one host are never gathered in a task.

Cases: null and empty pages have empty text; cut-off and ill-nested pages are read as far as they go; a host with one page has
no template and its page is read by containers alone; a null url is a host of its own; repeated rows get equal text; other columns are ignored.
"""

from __future__ import annotations

import re
from collections import Counter
from collections.abc import Iterator
from html import unescape

import pandas as pd
from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

from .common import stash

# Element names and boilerplate words (fixed values)
INLINE = frozenset("a abbr acronym b bdi bdo big cite code data del dfn em font i ins kbd label mark nobr q rp rt ruby s samp small span strike strong sub sup time tt u var wbr".split())
VOID = frozenset("area base br col embed hr img input link meta param source track wbr".split())
UNSEEN = frozenset("script style noscript template textarea title iframe object svg math canvas select option button datalist audio video head".split())
RAW = frozenset("script style noscript template textarea title iframe xmp".split())
APART = frozenset("nav header footer aside form menu dialog fieldset".split())
CLOSES_P = frozenset("address article aside blockquote details dialog div dl fieldset figcaption figure footer form h1 h2 h3 h4 h5 h6 header hr main menu nav ol p pre section table ul".split())
BOILERPLATE = re.compile(
    r"(?:^|[-_\s])(?:ad|ads|adv|advert|adverts|advertisement|advertising|banner|sponsor|sponsored|promo|promoted|nav|navbar|navigation|menu|menubar|breadcrumb|breadcrumbs|"
    r"sidebar|sidenav|aside|widget|widgets|related|recommended|footer|header|masthead|topbar|cookie|cookies|consent|gdpr|notice|notices|notification|alert|popup|modal|overlay|"
    r"newsletter|subscribe|subscription|signup|login|search|share|sharing|social|comment|comments|commentlist|respond|replies|reply|disqus|pagination|pager|toolbar|skip|"
    r"copyright|legal|disclaimer|outbrain|taboola|tags|meta)(?:$|[-_\s\d])",
    re.I,
)
ROLES = frozenset("navigation banner contentinfo complementary search form dialog alert alertdialog menu menubar".split())
ARTICLE = re.compile(r"(?:^|[-_\s])(?:article|articlebody|post|entry|story|main|content)(?:$|[-_\s\d])", re.I)

_MARKUP = re.compile(r"<!--.*?(?:-->|\Z)|<!\[CDATA\[.*?(?:\]\]>|\Z)|<[!?][^>]*(?:>|\Z)|<(/?)([a-zA-Z][^\s/>]*)((?:[^>\"']|\"[^\"]*\"|'[^']*'|[\"'])*?)(?:>|\Z)", re.S)
_ATTRIBUTE = re.compile(r"([^\s=\"'/>]+)(?:\s*=\s*(?:\"([^\"]*)\"|'([^']*)'|([^\s\"'>]+)))?")


class Box:
    """An open container."""

    __slots__ = ("name", "path", "apart", "article", "unseen")

    def __init__(self, name: str, path: str, apart: bool, article: bool, unseen: bool):
        self.name, self.path, self.apart, self.article, self.unseen = name, path, apart, article, unseen


def _open(name: str, attributes: str, parent: Box) -> Box:
    label = role = hidden = ""
    if attributes.strip(" /\n\t\r"):
        found = {m.group(1).lower(): m.group(2) or m.group(3) or m.group(4) or "" for m in _ATTRIBUTE.finditer(attributes)}
        label, role = f"{found.get('class', '')} {found.get('id', '')}".strip(), found.get("role", "").lower()
        hidden = "hidden" if "hidden" in found or found.get("aria-hidden") == "true" or "display:none" in found.get("style", "").replace(" ", "").lower() else ""
    article = name in ("article", "main") or role in ("main", "article") or bool(label and ARTICLE.search(label) and name in ("div", "section", "td"))
    own_head = name == "header" and parent.article  # an article's own heading
    apart = not own_head and (name in APART or role in ROLES or hidden != "" or bool(label and not (article and name in ("article", "main")) and name != "body" and BOILERPLATE.search(label)))
    return Box(name, f"{parent.path}>{name}.{label}" if label else f"{parent.path}>{name}", parent.apart or apart, parent.article or (article and not apart), parent.unseen or name in UNSEEN)


def blocks_of(html: str | None) -> tuple[list[tuple[str, str, bool, bool]], Counter]:
    """Text blocks (path, text, apart, in an article) in page order, and how often each container occurs."""
    out: list[tuple[str, str, bool, bool]] = []
    boxes: Counter[str] = Counter()
    root = Box("", "", False, False, False)
    stack, parts = [root], []

    def close_block() -> None:
        if parts:
            text = " ".join(unescape("".join(parts)).split())
            parts.clear()
            if text:
                top = stack[-1]
                out.append((top.path, text, top.apart, top.article))

    def keep(text: str) -> None:
        if text and not stack[-1].unseen:
            parts.append(text)

    at, html = 0, html or ""
    size = len(html)
    while at < size:
        found = _MARKUP.search(html, at)
        if found is None:
            keep(html[at:])
            break
        keep(html[at : found.start()])
        at = found.end()
        name = found.group(2)
        if name is None:
            if found.group().startswith("<![CDATA["):
                keep(found.group()[9:].removesuffix("]]>"))
            continue
        name = name.lower()
        if name in INLINE:
            continue
        if found.group(1):
            if name == "p" and all(b.name != "p" for b in stack):
                close_block()
                continue
            for i in range(len(stack) - 1, 0, -1):
                if stack[i].name == name:
                    close_block()
                    del stack[i:]
                    break
            continue
        close_block()
        if name in VOID:
            continue
        if name in CLOSES_P and stack[-1].name == "p" or name == stack[-1].name and name in ("li", "dt", "dd", "tr", "td", "th", "option", "p"):
            stack.pop()
        if name == "body":  # what a cut-off head left open
            del stack[2 if len(stack) > 1 and stack[1].name == "html" else 1 :]
        box = _open(name, found.group(3), stack[-1])
        boxes[box.path] += 1
        if name in RAW:
            end = re.compile(rf"</{name}\s*>", re.I).search(html, at)
            at = end.end() if end else size
            continue
        if not found.group(3).endswith("/") or name not in ("svg", "math"):
            stack.append(box)
    close_block()
    return out, boxes


def _number(text: str) -> int:
    from xxhash import xxh64_intdigest

    return int.from_bytes(xxh64_intdigest(text.encode("utf-8", "surrogatepass")).to_bytes(8, "big"), "big", signed=True)


def block_token(path: str, text: str) -> int:
    return _number(f"{path}\x00{text}")


ROOT, LARGE = _number(""), 3  # the token that every page has once; words that make a class of text large


def host_of(url: Column) -> Column:
    return F.lower(F.coalesce(F.regexp_extract(url, r"^[a-zA-Z][a-zA-Z0-9+.-]*://(?:[^/@]*@)?([^/:?#]+)", 1), F.lit("")))


def page_tokens(pages: DataFrame) -> DataFrame:
    """(host, page, tokens, marks, words, inside) for every page of ``pages(host, html)`` that has a token; a page is known by its content.

    ``marks`` hash page and count; containers have no words; ``inside`` tells text in an article.
    """

    def tokens(batches: Iterator[pd.DataFrame]) -> Iterator[pd.DataFrame]:
        for batch in batches:
            rows = []
            for host, html in zip(batch["host"], batch["html"]):
                blocks, boxes = blocks_of(html)
                if not blocks and not boxes:
                    continue
                page = _number(html)
                texts: Counter[int] = Counter()
                about: dict[int, tuple[int, bool]] = {}
                for path, text, _, article in blocks:
                    token = block_token(path, text)
                    texts[token] += 1
                    about[token] = (len(text.split()), article)
                found = [(ROOT, 1, 0, False), *((_number(p), n, 0, False) for p, n in boxes.items()), *((t, n, *about[t]) for t, n in texts.items())]
                rows.append((host, page, [x[0] for x in found], [_number(f"{page}|{x[1]}") for x in found], [x[2] for x in found], [x[3] for x in found]))
            yield pd.DataFrame(rows, columns=["host", "page", "tokens", "marks", "words", "inside"])

    return pages.mapInPandas(tokens, "host string, page long, tokens array<long>, marks array<long>, words array<int>, inside array<boolean>")


def templates(pages: DataFrame, support: float = 0.5) -> DataFrame:
    """(host, fixed): tokens of text that the valid classes of each host hold, from ``pages(host, html)``."""
    lists = ["tokens", "marks", "words", "inside"]
    distinct = page_tokens(pages).groupBy("host", "page").agg(F.any_value(F.struct(*lists)).alias("of_page")).select("host", "of_page.*")
    each = distinct.select("host", F.explode(F.arrays_zip(*lists)).alias("x")).select("host", *[F.col(f"x.{c}").alias(c) for c in lists])
    counted = each.groupBy("host", F.col("tokens").alias("token")).agg(
        F.count(F.lit(1)).alias("pages"), F.bit_xor("marks").alias("vector"), F.max("words").alias("words"), F.bool_or("inside").alias("inside")
    )
    held = stash(counted.where("pages > 1"), "tokens")
    sizes = held.where(F.col("token") == ROOT).select("host", F.col("pages").alias("all_pages"))
    likely = held.join(sizes, "host").where((F.col("pages") >= support * F.col("all_pages")) & (F.col("pages") >= F.when(F.col("inside"), 3).otherwise(2)))
    # an equivalence class: one occurrence vector; it nests in the page's frame by a container of its own, or is large enough to stand in another class's
    classes = likely.groupBy("host", "pages", "vector").agg(
        F.bool_or(F.col("words") == 0).alias("framed"), F.sum("words").alias("words"), F.collect_list(F.when(F.col("words") > 0, F.col("token"))).alias("texts")
    )
    valid = classes.where((F.col("framed") | (F.col("words") >= LARGE)) & (F.size("texts") > 0))
    return valid.groupBy("host").agg(F.flatten(F.collect_list("texts")).alias("fixed"))


def main_text(html: str | None, fixed: frozenset[int] | set[int] = frozenset()) -> str:
    """The article's text, given the tokens of text that the host's template fixes."""
    blocks, _ = blocks_of(html)
    own = [b for b in blocks if not b[2]]
    slots = [b for b in own if block_token(b[0], b[1]) not in fixed] if fixed else own
    for part in (slots, own):
        if part:
            return " ".join(b[1] for b in [b for b in part if b[3]] or part)
    return ""


def extracted(pages: DataFrame, id_column: str = "page_id", support: float = 0.5) -> DataFrame:
    """(page_id, url, text, n_chars) for every row of ``pages(page_id, url, html)``."""
    ready = pages.select(F.col(id_column).alias("page_id"), "url", "html", host_of(F.col("url")).alias("host"))
    found = templates(ready.select("host", "html"), support)

    @F.pandas_udf("string")
    def text(htmls: pd.Series, fixed: pd.Series) -> pd.Series:
        return pd.Series([main_text(h, set(f) if f is not None and len(f) else frozenset()) for h, f in zip(htmls, fixed)])

    read = ready.join(stash(found, "templates"), "host", "left").select("page_id", "url", text("html", "fixed").alias("text"))
    return read.withColumn("n_chars", F.char_length("text").cast("long"))
