"""Main text of web pages by site style trees.

Pages of one host are merged into one tree: a node is an element with its class,
below its parent. Two measures say how much a node differs over the distinct pages of the host.
Content importance looks at the blocks of text that stand in it: a block that c of m pages
hold has the entropy log(c) / log(m), and one minus the mean entropy is the importance.
Presentation importance is the same measure over the styles of the node's blocks, the sequences of
elements inside them; with l styles it has the weight 1 - 0.9^l against the content. A node is
noise, and its text is removed, where both lie under ``IMPORTANCE``: then it and all that it
shows are alike all over the host. Furniture repeats and scores near zero; articles differ
and score near one. On m pages both are drawn towards one by the share 1 / m, so a host of few
pages, whose entropies say little, keeps what it has, without a step at any number of pages.

Each distinct page counts once (pages are distinct if their texts are), so that copies of
an article do not make it look like furniture. The tree decides inside articles and outside.
Beside it, what elements say of themselves holds for every page, since adverts and menus may
change from page to page: navigation, headers, footers, asides, forms, adverts, notices and
comments are no text; and if a page marks an article or main part, text outside it is none.

Only (host, node, style or block) and a hash of the page are shuffled, each once per task; the noise
of each host is small and is sent to the pages where its size, which is counted, allows, else
the pages are dealt by host and a salt. Null or empty html gives an empty text; pages without a host
are read by themselves; repeated rows count as one page; an empty table gives an empty one.
"""

from __future__ import annotations

import html as entities
import re

import pyarrow as pa
import xxhash
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from . import common

#: Nodes below this importance are noise.
IMPORTANCE, STYLE_BASE = 0.15, 0.9
#: Noise nodes that are sent to all tasks at most, and the parts of a host beyond that.
SENT, SALT = 1_000_000, 16

_TAG = re.compile(r"""<!--.*?(?:-->|\Z)|<!\[CDATA\[.*?\]\]>|<[!?][^>]*>|<(/?)([a-zA-Z][^\s/>]*)((?:[^>"']|"[^"]*"|'[^']*')*)>""", re.S)
_LOOSE = re.compile(r"<(/?)([a-zA-Z][^\s/>]*)([^>]*)>")
_ATTR = re.compile(r"""([a-zA-Z-]+)\s*=\s*(?:"([^"]*)"|'([^']*)'|([^\s"'>]+))""")
# Fixed values of HTML.
VOID = frozenset("area base br col embed hr img input link meta param source track wbr".split())
RAW = frozenset("script style noscript template iframe svg math object canvas textarea select option button title head".split())
INLINE = frozenset("a abbr acronym b bdi bdo big cite code data del dfn em font i ins kbd label mark q rp rt ruby s samp small span strike strong sub sup time tt u var wbr".split())
CLOSES_P = frozenset("address article aside blockquote details div dl fieldset figure footer form h1 h2 h3 h4 h5 h6 header hr main nav ol p pre section table ul".split())
FURNITURE = frozenset("nav header footer aside form menu dialog fieldset figure-nav".split())
ROLES = frozenset("navigation banner contentinfo complementary search form dialog alert menu menubar alertdialog".split())
_NAMES = re.compile(
    r"(?:^|[-_\s])(?:ads?|advert\w*|adsense|sponsor\w*|promo\w*|banner|nav\w*|menu\w*|breadcrumbs?|head|header|masthead|foot|footer|site-info|sidebar\w*|side|aside|widget\w*|cookies?|consent|gdpr|notice\w*|notification\w*|alert|popup|modal|overlay|"
    r"comments?|commentlist|reply|replies|respond|disqus|share|sharing|social|follow|related|recommend\w*|newsletter|subscribe\w*|signup|login|search\w*|form|pagination|pager|toolbar|skip|tags?|copyright|legal|disclaimer)(?:$|[-_\s\d])",
    re.I,
)
#: Names that parts of an article may carry too, and so say nothing inside one.
_NAMES_INSIDE = re.compile(
    r"(?:^|[-_\s])(?:ads?|advert\w*|adsense|sponsor\w*|promo\w*|nav\w*|menu\w*|breadcrumbs?|sidebar\w*|aside|widget\w*|cookies?|consent|gdpr|"
    r"comments?|commentlist|replies|respond|disqus|share|sharing|social|related|recommend\w*|newsletter|subscribe\w*|signup|login|pagination|pager|toolbar)(?:$|[-_\s\d])",
    re.I,
)
_HEADINGS = frozenset("h1 h2 h3 h4 h5 h6".split())


def furniture(tag: str, attributes: str, inside: bool = False) -> tuple[bool, str]:
    """Whether an element says that it is no part of the article; its class. ``inside``: it stands in an article."""
    if not attributes or "=" not in attributes:
        return tag in FURNITURE, ""
    found = {k.lower(): a or b or c for k, a, b, c in _ATTR.findall(attributes)}
    name = found.get("class", "")
    bad = tag in FURNITURE or found.get("role", "").lower() in ROLES or "hidden" in found or found.get("aria-hidden") == "true" or "display:none" in found.get("style", "").replace(" ", "").lower()
    if tag not in ("body", "html", "article", "main") or "comment" in name.lower():
        names = _NAMES_INSIDE if inside or tag in _HEADINGS else _NAMES
        bad = bad or bool(names.search(name)) or bool(names.search(found.get("id", "")))
    return bad, re.sub(r"\d+", "0", name)


class _Open:
    """An open element: its tag, node and style, and what holds for its text."""

    __slots__ = ("tag", "node", "bad", "inside", "block")

    def __init__(self, tag: str, node: int, bad: bool, inside: bool, block):
        self.tag, self.node, self.bad, self.inside = tag, node, bad, inside
        #: The innermost element around this one, itself included, that is no inline one.
        self.block = block or self


def _hash(s: str, seed: int = 0) -> int:
    return xxhash.xxh64_intdigest(s.encode(), seed) - (1 << 63)


def blocks(page: str | None):
    """(node, style, inside article, text) of every block of a page, in order.

    A node is a number made of the elements and classes from the root, a style one made of
    the inline elements around the block's text; text is decoded, its white space single.
    Furniture is left out. The time taken grows with the length of the page alone.
    """
    page = page or ""
    out, text, style = [], [], []
    stack = [_Open("", 0, False, False, None)]
    open_tags: dict[str, int] = {}
    at, size = 0, len(page)
    owner = stack[0]

    def close():
        s = " ".join(entities.unescape("".join(text)).split())
        text.clear()
        if s:
            out.append((owner.node, _hash(" ".join(style)), owner.inside, s))
        style.clear()

    def pop() -> str:
        tag = stack.pop().tag
        open_tags[tag] -= 1
        return tag

    while at < size:
        m = _TAG.search(page, at)
        if m is not None and (loose := page.find("<", m.start() + 1, m.end())) != -1 and m[2] and "\n<" in m[0]:
            m = _LOOSE.search(page, m.start()) or m
        start = m.start() if m else size
        if start > at and not stack[-1].bad:
            text.append(page[at:start])
        if m is None:
            break
        at = m.end()
        tag = m[2].lower() if m[2] else ""
        if not tag:
            continue
        if m[1]:
            if open_tags.get(tag):
                if tag not in INLINE:
                    close()
                while pop() != tag:
                    pass
                if tag not in INLINE:
                    owner = stack[-1].block
            continue
        if tag in RAW and tag != "head":
            end = re.compile(rf"</{tag}\s*>", re.I).search(page, at)
            if tag in ("button", "option", "select", "object", "title", "textarea"):
                close()
            at = end.end() if end else size
            continue
        if tag in VOID:
            if tag in ("br", "hr"):
                text.append(" ")
            continue
        if m[3].endswith("/") and tag not in INLINE and tag not in CLOSES_P:
            continue
        if tag not in INLINE:
            close()
            if tag in CLOSES_P and open_tags.get("p"):
                while pop() != "p":
                    pass
            elif tag in ("li", "dt", "dd", "tr", "td", "th") and stack[-1].tag == tag:
                pop()
        else:
            style.append(tag)
        above = stack[-1]
        bad, name = furniture(tag, m[3], above.inside)
        node = above.node if tag in INLINE else _hash(f"{tag}.{name}", above.node & (1 << 64) - 1)
        stack.append(_Open(tag, node, above.bad or bad or tag == "head", above.inside or tag in ("article", "main"), above.block if tag in INLINE else None))
        open_tags[tag] = open_tags.get(tag, 0) + 1
        if tag not in INLINE:
            owner = stack[-1]
    close()
    return out


def article(page: str | None) -> list:
    """The blocks of a page that are no furniture: those in an article, if it marks one."""
    found = blocks(page)
    return [b for b in found if b[2]] if any(b[2] for b in found) else found


def main_text(page: str | None, noise: frozenset = frozenset()) -> str:
    """Text of a page without furniture and without the nodes that are noise."""
    return " ".join(b[3] for b in article(page) if b[0] not in noise)


def host(url) -> str:
    m = re.match(r"(?:[a-zA-Z][\w+.-]*:)?//(?:[^/@?#]*@)?([^/:?#]+)", url or "")
    return m[1].lower() if m else ""


_HOST = r"^(?:[a-zA-Z][\w+.-]*:)?//(?:[^/@?#]*@)?([^/:?#]+)"
BLOCK_OF, STYLE_OF, PAGE_OF = 0, 1, 2


def style_tree(pages: DataFrame) -> DataFrame:
    """(host, node, pages, content, presentation, importance) of the nodes of each host's tree that show text."""

    def work(batches):
        schema = pa.schema([("host", pa.string()), ("node", pa.int64()), ("kind", pa.int8()), ("shown", pa.int64()), ("page", pa.int64())])
        for b in batches:
            rows = set()
            for url, page in zip(b.column(0), b.column(1)):
                at = host(url.as_py())
                found = article(page.as_py()) if at else []
                if found:
                    own = _hash("\0".join(x[3] for x in found))
                    rows.add((at, 0, PAGE_OF, 0, own))
                    rows.update(x for node, style, _, text in found for x in ((at, node, BLOCK_OF, _hash(text), own), (at, node, STYLE_OF, style, own)))
            if rows:
                yield common.batch(schema, *zip(*rows))

    seen = common.columns(pages, ["url", "html"]).mapInArrow(work, "host string, node long, kind byte, shown long, page long").distinct()
    # Written, as both the nodes and the numbers of pages are taken from it.
    counted = common.Stage(pages.sparkSession, "pages").save(seen.groupBy("host", "node", "kind", "shown").agg(F.count("*").alias("c")), "counted")
    nodes = counted.filter(F.col("kind") != PAGE_OF).groupBy("host", "node").agg(
        *[F.sum(F.when(F.col("kind") == k, F.col("c") * F.log("c"))).alias(f"spread{k}") for k in (BLOCK_OF, STYLE_OF)],
        *[F.sum(F.when(F.col("kind") == k, F.col("c"))).alias(f"n{k}") for k in (BLOCK_OF, STYLE_OF)],
        F.count_if(F.col("kind") == STYLE_OF).alias("styles"),
    )
    sites = counted.filter(F.col("kind") == PAGE_OF).select("host", F.col("c").alias("pages"))
    m = F.col("pages")
    differs = lambda k: F.when(m > 1, 1 - (m - 1) / m * F.col(f"spread{k}") / F.col(f"n{k}") / F.log(m)).otherwise(F.lit(1.0))
    rows = nodes.join(sites, "host").withColumn("content", differs(BLOCK_OF)).withColumn("presentation", differs(STYLE_OF))
    weight = 1 - F.pow(F.lit(STYLE_BASE), F.col("styles"))
    both = weight * F.col("presentation") + (1 - weight) * F.col("content")
    return rows.select("host", "node", "pages", "content", "presentation", F.greatest("content", both).alias("importance"))


def extract(pages: DataFrame, importance: float = IMPORTANCE) -> DataFrame:
    """One row per page: page_id, url, text, n_chars (code points). Importance 0: without the tree."""
    spark = pages.sparkSession
    common.small_batches(spark)
    stage = common.Stage(spark, "pages")
    noise = stage.save(style_tree(pages).filter(F.col("importance") < importance).select("host", "node"), "noise")
    low = noise.groupBy("host").agg(F.collect_set("node").alias("low"))
    rows = common.columns(pages, ["page_id", "url", "html"]).withColumn("host", F.lower(F.regexp_extract("url", _HOST, 1)))
    if noise.count() <= SENT:
        joined = rows.join(F.broadcast(low), "host", "left")
    else:
        salted = low.withColumn("salt", F.explode(F.array(*map(F.lit, range(SALT)))))
        joined = rows.withColumn("salt", F.pmod(F.xxhash64("page_id", "url"), F.lit(SALT)).cast("int")).join(salted, ["host", "salt"], "left")

    def work(batches):
        schema = pa.schema([("page_id", pa.int64()), ("url", pa.string()), ("text", pa.string()), ("n_chars", pa.int64())])
        for b in batches:
            texts = [main_text(page.as_py(), frozenset(low.as_py() or ())) for page, low in zip(b.column(2), b.column(3))]
            yield common.batch(schema, b.column(0), b.column(1), texts, [len(t) for t in texts])

    return joined.select("page_id", "url", "html", "low").mapInArrow(work, "page_id long, url string, text string, n_chars long")
