"""Main text of web pages by site style trees.

Pages of a host are merged by *style path* (the tags with class and id from the root down, containers also with their place
among siblings of that name, so that classless pages have a tree too).  For a node of the merged tree with m pages, a block of
text that n of them share has entropy log n / log m; the content importance is one less the mean of these over the blocks below
the node, the presentation importance the entropy (base m) of the node's child sequences, and the composite
(1 - g^l) presentation + g^l content for l distinct child sequences, times the share of its words that stand outside of links.

Beside what pages repeat, the tree tells where a host's pages have their words: branches of the page itself, or of an element
that merely wraps it, that hold few of them are worth as much less (headings apart).  Branches of low importance are removed from
each page.  One with more than half of the words never is: pages that are copies of one another still have a text.

The tree is joined by what markup itself says, which one page can tell: elements and names of navigation, advertising, forms,
comments and the like never hold main text; inside an article (or main) headings and paragraphs stay whatever their importance,
since copies of an article are still its text; and where a page has an article, only that counts.  ``markup=False`` leaves the
tree alone.
"""

from __future__ import annotations

import html
import re
from collections import Counter
from collections.abc import Iterator
from urllib.parse import urlsplit

import pyarrow as pa
import xxhash
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from .common import spool, tidy

DECAY = 0.9
LEAST_IMPORTANCE = 0.3
#: A branch of the page with less than this share of the host's words loses importance in proportion; an element with at least
#: ``WRAPPER`` of them, half in one container, only wraps the page.
LEAST_SHARE, WRAPPER = 0.2, 0.9
#: Most branches that are sent to every task; beyond, they are joined to the pages by host.
MAX_BROADCAST = 200_000

# Fixed values of HTML.
VOID = frozenset("area base br col embed hr img input link meta param source track wbr".split())
RAW = frozenset("script style textarea title noscript template iframe xmp noembed noframes svg math object canvas".split())
BLOCK = frozenset("html body address article aside blockquote center dd details dialog dir div dl dt fieldset figcaption figure footer form h1 h2 h3 h4 h5 h6 header hgroup hr legend li main menu nav ol p pre section summary table tbody td tfoot th thead tr ul".split())
HEADINGS = frozenset("h1 h2 h3 h4 h5 h6".split())
CONTAINERS = BLOCK - HEADINGS - frozenset("html body p li dt dd tr td th pre blockquote hr figcaption legend summary".split())
CLOSES_P = BLOCK - {"html", "body", "td", "th", "tr", "tbody", "thead", "tfoot"}
#: A start tag ends an open element of these, up to the element that bounds the search.
SIBLINGS = {"li": ({"li"}, {"ul", "ol", "menu"}), "dt": ({"dt", "dd"}, {"dl"}), "dd": ({"dt", "dd"}, {"dl"}), "tr": ({"tr", "td", "th"}, {"table", "tbody", "thead", "tfoot"}), "td": ({"td", "th"}, {"tr"}), "th": ({"td", "th"}, {"tr"}), "option": ({"option"}, {"select"})}
NOISE_TAGS = frozenset("nav header footer aside form menu button select dialog head label fieldset".split())
KEPT_IN_ARTICLE = frozenset("h1 h2 h3 h4 h5 h6 p pre blockquote".split())
NOISE_ROLES = frozenset("navigation banner contentinfo complementary search dialog alert form menu menubar".split())
NOISE_NAMES = re.compile(
    r"(?:^|[-_\s])(?:ad|ads|advert\w*|adbox|adsense|sponsor\w*|promo\w*|banner|cookie\w*|consent|notice|gdpr|popup|modal|newsletter|subscribe|signup|"
    r"nav|navbar|navigation|menu\w*|breadcrumbs?|topbar|sidebar|side|rail|widget\w*|header|masthead|footer|copyright|legal|comments?|commentlist|"
    r"disqus|replies|respond|reader-comments|share|sharing|social|related|recommend\w*|pagination|pager|login|search\w*|toolbar|skip-link)(?:$|[-_\s\d])",
    re.IGNORECASE,
)
#: Names of an article's own parts, which are no noise whatever else they hold.
OWN_NAMES = re.compile(r"(?:^|\s)(?:article|post|entry|story|content)[-_]?(?:header|title|headline|body|text|content)(?:$|\s)", re.IGNORECASE)
ARTICLE = frozenset({"article", "main"})

_TAG = re.compile(r"""<!--.*?(?:--!?>|\Z)|<[!?][^>]*(?:>|\Z)|<(/?)([A-Za-z][^\s/>]*)((?:"[^"]*"|'[^']*'|[^>"'])*)(?:>|\Z)""", re.DOTALL)
_ATTRIBUTE = re.compile(r"""(?:^|\s)(class|id|role|hidden|aria-hidden)(?:\s*=\s*(?:"([^"]*)"|'([^']*)'|([^\s"'>]+)))?""", re.IGNORECASE)
_DIGITS = re.compile(r"\d+")


class Element:
    __slots__ = ("article", "children", "name", "noise", "path", "places", "tag")

    def __init__(self, tag: str, name: str, path: int, noise: bool, article: bool) -> None:
        self.tag, self.name, self.path, self.noise, self.article = tag, name, path, noise, article
        self.children: list[str] = []
        self.places: Counter = Counter()


class Block:
    """A stretch of text in one block element: its style paths from the root down (with tags), how many of its words are in
    links, and whether markup calls it noise or article."""

    __slots__ = ("article", "linked", "noise", "paths", "tags", "text")

    def __init__(self, stack: list[Element], text: str, linked: int) -> None:
        self.text, self.linked = text, linked
        self.paths, self.tags = [e.path for e in stack], [e.tag for e in stack]
        self.noise, self.article = stack[-1].noise, stack[-1].article


def parse(page: str | None) -> tuple[list[Block], list[tuple[int, int]]]:
    """Blocks of a page in order, and (style path, hash of the child sequence) of its elements.  Bad nesting is repaired, an
    unfinished tag at the end dropped."""
    stack = [Element("", "", 0, False, False)]
    blocks: list[Block] = []
    shapes: list[tuple[int, int]] = []
    pieces: list[str] = []
    linked = 0

    def flush() -> None:
        nonlocal linked
        if pieces:
            text = " ".join(html.unescape("".join(pieces)).split())
            pieces.clear()
            if text:
                blocks.append(Block(stack, text, linked))
            linked = 0

    def close(down_to: int) -> None:
        while len(stack) > down_to:
            if stack[-1].tag in BLOCK:
                flush()
            e = stack.pop()
            shapes.append((e.path, xxhash.xxh64_intdigest(" ".join(e.children)) >> 1))

    def open_at(wanted: set[str] | frozenset[str], bound: set[str] | frozenset[str]) -> int:
        for i in range(len(stack) - 1, 0, -1):
            if stack[i].tag in wanted:
                return i
            if stack[i].tag in bound:
                break
        return 0

    source, at = page or "", 0
    for m in iter(lambda: _TAG.search(source, at), None):
        if m.start() > at:
            pieces.append(source[at : m.start()])
            if any(e.tag == "a" for e in stack):
                linked += len(pieces[-1].split())
        at = m.end()
        if m[2] is None:
            continue
        tag = m[2].lower()
        if m[1]:
            if tag == "p" and not open_at({"p"}, frozenset()):
                flush()
            elif i := open_at({tag}, frozenset() if tag in BLOCK else BLOCK):
                close(i)
            continue
        if tag in RAW:
            end = re.compile(rf"</{re.escape(tag)}(?=[\s/>])[^>]*>", re.IGNORECASE).search(source, at)
            at = end.end() if end else len(source)
            continue
        if tag in ("html", "body") and any(e.tag == tag for e in stack):
            continue
        if tag in CLOSES_P and (i := open_at({"p"}, {"button", "table", "td", "th"})):
            close(i)
        if tag in SIBLINGS and (i := open_at(*SIBLINGS[tag])):
            close(i)
        if tag in BLOCK:
            flush()
            if tag == "body" and len(stack) > 1 and (i := open_at({"head"}, frozenset())):
                close(i)
        elif tag == "br":
            pieces.append(" ")
        if tag in VOID:
            stack[-1].children.append(tag)
            continue
        named = {a[1].lower(): a[2] or a[3] or a[4] or "" for a in _ATTRIBUTE.finditer(m[3])} if m[3] else {}
        if named:
            label = " ".join(sorted(f"{k}={_DIGITS.sub('0', named[k])}" for k in ("class", "id") if named.get(k)))
        else:
            label = ""
        name = f"{tag} {label}" if label else tag
        up = stack[-1]
        noise = up.noise or tag in NOISE_TAGS or "hidden" in named or named.get("aria-hidden", "").lower() == "true" or named.get("role", "").lower() in NOISE_ROLES or tag not in ("html", "body") and any(NOISE_NAMES.search(OWN_NAMES.sub(" ", named[k])) for k in ("class", "id") if k in named)
        up.children.append(name)
        if tag in CONTAINERS:
            up.places[name] += 1
            place = f"{name}#{up.places[name]}"
        else:
            place = name
        stack.append(Element(tag, name, xxhash.xxh64_intdigest(f"{up.path}/{place}") >> 1, noise, up.article or tag in ARTICLE))
    if at < len(source):
        pieces.append(source[at:])
    flush()
    close(1)
    return blocks, shapes


def host_of(url: str | None) -> str:
    try:
        return (urlsplit(url or "").hostname or "").lower()
    except ValueError:
        return ""


def main_text(page: str | None, removed: frozenset[int] | set[int] = frozenset(), markup: bool = True) -> str:
    """Blocks that are neither noise by their markup nor under a removed style path, joined by line feeds; without ``markup`` the
    removed paths alone decide."""
    blocks, _ = parse(page)
    if not markup:
        return "\n".join(b.text for b in blocks if not removed.intersection(b.paths))
    kept = [b for b in blocks if not b.noise]
    if any(b.article for b in kept):
        kept = [b for b in kept if b.article]
    out = []
    for b in kept:
        low = [t for p, t in zip(b.paths, b.tags, strict=True) if p in removed and t not in ("", "html", "body") and t not in ARTICLE]
        if not low or b.article and all(t in KEPT_IN_ARTICLE for t in low):
            out.append(b.text)
    return "\n".join(out)


def style_counts(pages: DataFrame) -> DataFrame:
    """(host, path, kind, feature, n): pages of a host whose node has the feature; kinds: m the node itself (feature: its tag's
    kind, 1 heading, 2 container), c a block of text below it, p a sequence of children, u the node above; and sums over pages,
    w words and l words in links.  Path 0 is the page."""

    def each(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        held: Counter = Counter()

        def rows() -> pa.RecordBatch:
            columns = list(zip(*held, strict=True)) or [(), (), (), ()]
            kinds = [pa.string(), pa.int64(), pa.string(), pa.int64()]
            return pa.record_batch([*(pa.array(c, k) for c, k in zip(columns, kinds, strict=True)), pa.array(list(held.values()), pa.int64())], names=["host", "path", "kind", "feature", "n"])

        for batch in batches:
            for url, page in zip(batch["url"].to_pylist(), batch["html"], strict=True):
                host, seen = host_of(url), set()
                blocks, shapes = parse(page.as_py())
                for b in blocks:
                    text, words, above = xxhash.xxh64_intdigest(b.text) >> 1, len(b.text.split()), 0
                    for path, tag in zip(b.paths, b.tags, strict=True):
                        if tag == "" or tag not in ("html", "body") and tag in BLOCK:
                            seen |= {(path, "c", text), (path, "m", 1 if tag in HEADINGS else 2 if tag in CONTAINERS else 0), (path, "u", above)}
                            held[host, path, "w", 0] += words
                            held[host, path, "l", 0] += min(words, b.linked)
                            above = path
                nodes = {p for p, kind, _ in seen if kind == "m"}
                seen |= {(p, "p", s) for p, s in shapes if p in nodes}
                held.update((host, *s) for s in seen)
                if len(held) > 200_000:
                    yield rows()
                    held.clear()
        yield rows()

    parts = pages.select("url", "html").mapInArrow(tidy(each), "host string, path long, kind string, feature long, n long")
    return parts.groupBy("host", "path", "kind", "feature").agg(F.sum("n").alias("n"))


def importance(counts: DataFrame) -> DataFrame:
    """(host, path, pages, presentation, content, importance) of every node of the style trees, the page itself apart."""

    def of(kind: str, value):
        return F.sum(F.when(F.col("kind") == kind, value).otherwise(0.0))

    n = F.col("n")
    nodes = counts.groupBy("host", "path").agg(
        F.max(F.when(F.col("kind") == "m", n)).alias("pages"), F.max(F.when(F.col("kind") == "m", F.col("feature"))).alias("tag"), F.max(F.when(F.col("kind") == "u", F.col("feature"))).alias("above"),
        F.max(F.when(F.col("kind") == "w", n)).alias("words"), F.max(F.when(F.col("kind") == "l", n)).alias("linked"),
        of("c", F.log(n)).alias("shared"), of("c", F.lit(1.0)).alias("texts"),
        of("p", n.cast("double")).alias("shapes"), of("p", n * F.log(n)).alias("weighed"), of("p", F.lit(1.0)).alias("forms"),
    )
    base = F.log(F.col("pages"))
    several = F.col("pages") > 1
    nodes = nodes.withColumn("content", F.when(several, 1 - F.col("shared") / F.col("texts") / base).otherwise(1.0))
    nodes = nodes.withColumn("presentation", F.when(several & (F.col("shapes") > 0), F.least(F.lit(1.0), (F.log("shapes") - F.col("weighed") / F.col("shapes")) / base)).otherwise(F.when(several, 0.0).otherwise(1.0)))
    decay = F.pow(F.lit(DECAY), F.col("forms"))
    nodes = nodes.withColumn("own", ((1 - decay) * F.col("presentation") + decay * F.col("content")) * (1 - F.col("linked") / F.greatest("words", F.lit(1))))
    nodes = spool(nodes)  # it meets itself below
    # words of the whole page, and of the largest container below, by host and node; a node has one row, so no group is large
    page = nodes.where("path = 0").select("host", (F.col("words") / F.col("pages")).alias("page"))
    below = nodes.where("tag = 2").groupBy("host", F.col("above").alias("path")).agg(F.max("words").alias("below"))
    nodes = nodes.join(page, "host").join(below, ["host", "path"], "left")
    share = F.col("words") / F.col("pages") / F.greatest("page", F.lit(1.0))
    nodes = nodes.withColumns({"share": share, "wraps": (F.col("path") == 0) | (share >= WRAPPER) & (F.coalesce("below", F.lit(0)) * 2 >= F.col("words"))})
    up = nodes.where("wraps").select("host", F.col("path").alias("above"), F.lit(True).alias("free"))
    nodes = nodes.where("path <> 0").join(up, ["host", "above"], "left")
    weight = F.when(F.col("free") & ~F.col("wraps") & (F.col("tag") != 1), F.least(F.lit(1.0), F.col("share") / LEAST_SHARE)).otherwise(1.0)
    return nodes.select("host", "path", "pages", "presentation", "content", F.when(F.col("wraps") | (F.col("share") > 0.5), 1.0).otherwise(F.col("own") * weight).alias("importance"))


def removed_paths(pages: DataFrame) -> DataFrame:
    """(host, paths): the branches of each host's tree that are removed."""
    return spool(importance(style_counts(pages)).where(F.col("importance") < LEAST_IMPORTANCE).groupBy("host").agg(F.collect_set("path").alias("paths")))


def extract(pages: DataFrame, markup: bool = True) -> DataFrame:
    """(page_id, url, text) of every page (page_id, url, html); other columns aren't read.  Null html is empty, a null url has no
    host; repeated rows stay repeated, and an empty table gives an empty result."""
    low = removed_paths(pages)
    size = low.agg(F.sum(F.size("paths") + 1).alias("n")).first().n or 0
    kept = pages.select("page_id", "url", "html")
    schema = f"page_id {pages.schema['page_id'].dataType.simpleString()}, url string, text string"

    if size <= MAX_BROADCAST:
        shared = kept.sparkSession.sparkContext.broadcast({r.host: frozenset(r.paths) for r in low.collect()})

        def by_host(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
            for batch in batches:
                texts = [main_text(p.as_py(), shared.value.get(host_of(u), frozenset()), markup) for u, p in zip(batch["url"].to_pylist(), batch["html"], strict=True)]
                yield pa.record_batch([batch["page_id"], batch["url"], pa.array(texts, pa.string())], names=["page_id", "url", "text"])

        return kept.mapInArrow(tidy(by_host), schema)

    @F.pandas_udf("string")
    def host(urls):
        return urls.map(host_of, na_action=None)

    def joined(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in batches:
            texts = [main_text(p.as_py(), frozenset(x.as_py() or ()), markup) for p, x in zip(batch["html"], batch["paths"], strict=True)]
            yield pa.record_batch([batch["page_id"], batch["url"], pa.array(texts, pa.string())], names=["page_id", "url", "text"])

    return kept.withColumn("host", host("url")).join(low, "host", "left").mapInArrow(tidy(joined), schema)


def op5_site_style_tree(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Main text of every page."""
    found = extract(spark.read.parquet(f"{sf_dir}/pages.parquet"))
    return found.select("page_id", "url", "text", F.char_length("text").cast("long").alias("n_chars"))
