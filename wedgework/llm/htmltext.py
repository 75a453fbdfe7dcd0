"""Main text of web pages by site style trees.

Pages are parsed into blocks of text, each with its style path: the element names and class words from the root. The pages of one host
are merged into a style tree whose nodes are those paths. Of each node the host's pages give

* its presentation importance: the entropy of its layouts (the paths of the blocks below it, in order), over the logarithm of the pages;
* its content importance: the entropy of the texts it holds, measured likewise;
* its share of the pages' text, and the share of its text that is in links.

What a node shows is content * max(presentation, share, support). Text-flow elements (headings, paragraphs, lists, tables) are supported
by their parent as far as they aren't links; containers must show their own importance. So a menu, an advert or a footer goes although
its text changes on every page: its layout is the same and its share small; and a line that all pages have goes out of an article.
Evidence from few pages is mixed with a prior, which weighs as much as ``PRIOR_PAGES`` pages: -1 for nodes whose names say navigation,
header, footer, sidebar, notice or advert, which aren't supported by parents either, 1 below ``article`` and ``main``, else 0.5. Branches
of low importance are removed from each page of the host, top down.

By name alone, on any host, go only elements whose content isn't running text by definition (scripts, styles, forms, embedded objects and
drawings) and reader comments, which no statistic can tell from an article. Pages of equal text count as one page, so copies of an article
on one host don't remove it.

Statistics are sums by (host, path, text), aggregated before they are shuffled; a host with a third of all pages is thus no hot group.
Defined results: a null html is empty, an empty page has empty text; a page without url belongs to the host ''; repeated rows give
repeated rows; unclosed, crossed and cut-off markup is read as far as it goes; other columns are ignored.
"""

from __future__ import annotations

import html as entities
import re
from collections.abc import Iterator

import pandas as pd
import xxhash
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from .common import load, materialise

#: Element and class names.
RULED = frozenset("script style noscript template svg iframe object embed canvas audio video select option datalist button input textarea label form fieldset head title meta link".split())
RAW = frozenset("script style noscript template textarea title iframe svg".split())
VOID = frozenset("area base br col embed hr img input link meta param source track wbr".split())
FLOW = frozenset("h1 h2 h3 h4 h5 h6 p pre blockquote ul ol li dl dt dd table tbody thead tfoot tr td th figure summary details address center".split())
NAMED = frozenset("nav footer aside menu dialog".split())
BLOCKS = FLOW | NAMED | frozenset("article body div fieldset form header hr html main section".split())
CONTENT = ("article", "main")
COMMENTS = re.compile(r"(?:^|[-_\s])(?:comments?|comment\w*|disqus|replies|respond)(?:$|[-_\s\d])", re.I)
NOISE = re.compile(r"(?:^|[-_\s])(?:ads?|advert\w*|banner|breadcrumbs?|cookies?|consent|footer|menu|nav|navbar|navigation|newsletter|notice|pagination|popup|promo\w*|related|share|sharing|sidebar|signup|skip|social|sponsor\w*|subscribe|subscription|toolbar|widget)(?:$|[-_\s\d])", re.I)
#: These stand for the page's head only outside the content.
HEADS = re.compile(r"(?:^|[-_\s])(?:header|masthead|topbar)(?:$|[-_\s\d])", re.I)
_TAG = re.compile(r"<!--.*?(?:-->|$)|<![^>]*(?:>|$)|<\?[^>]*(?:>|$)|<(/?)([a-zA-Z][^\s/>]*)((?:[^>\"']|\"[^\"]*\"|'[^']*')*)(?:>|$)", re.S)
_ATTRIBUTE = re.compile(r"""\b(class|id|role)\s*=\s*(?:"([^"]*)"|'([^']*)'|([^\s"'>]+))""", re.I)
_CLOSES = {"p": {"p"}, "li": {"li"}, "dt": {"dt", "dd"}, "dd": {"dt", "dd"}, "tr": {"tr", "td", "th"}, "td": {"td", "th"}, "th": {"td", "th"}, "option": {"option"}}
_SPACE = re.compile(r"\s+")
#: Least importance of a node, and the pages whose evidence weighs as much as the prior.
IMPORTANCE = 0.2
PRIOR_PAGES = 4
#: Bytes of the removed paths of all hosts that are broadcast at most; beyond it the join is left to Spark, which splits large hosts.
BROADCAST_BYTES = 32 << 20


def host_of(url: str | None) -> str:
    m = re.match(r"\s*(?:[a-zA-Z][\w+.-]*:)?//(?:[^/?#@]*@)?([^/?#:]*)", url or "")
    return m[1].lower() if m else ""


def kind_of(name: str, marks: str, content: bool) -> str:
    """What an element's names say: n (noise), c (content), f (text flow) or o (any other container)."""
    if name in CONTENT:
        return "c"
    if name in ("html", "body"):
        return "o"
    if name in NAMED or name == "header" and not content or marks and (NOISE.search(marks) or not content and HEADS.search(marks)):
        return "n"
    return "f" if name in FLOW else "o"


def blocks(page: str) -> list[tuple[str, str, str, int]]:
    """(style path, kinds of its elements, text, characters in links) of each block, in page order; a narrow parser that never fails."""
    out: list[tuple[str, str, str, int]] = []
    stack: list[tuple[str, str, str, bool]] = [("", "", "", False)]  # name, path, kinds, ruled out
    parts: list[str] = []
    links = depth = 0  # characters in links of the block, and open links
    at = 0

    def put(text: str) -> None:
        nonlocal links
        parts.append(text)
        links += len(text) if depth else 0

    def flush() -> None:
        nonlocal links
        if parts:
            # references are decoded once all parts of a block are there; spaces inside become one
            text = _SPACE.sub(" ", entities.unescape("".join(parts))).strip()
            parts.clear()
            _, path, kinds, ruled = stack[-1]
            if text and not ruled:
                out.append((path, kinds, text, min(links, len(text))))
        links = 0

    while at < len(page):
        m = _TAG.search(page, at)
        if m is None:
            put(page[at:])
            break
        if m.start() > at:
            put(page[at : m.start()])
        at = m.end()
        if m[2] is None:
            continue
        name = m[2].lower()
        if m[1]:
            depth -= name == "a" and depth > 0
            for i in range(len(stack) - 1, 0, -1):
                if stack[i][0] == name:
                    if name in BLOCKS or name in RULED or stack[i][1:] != stack[i - 1][1:]:
                        flush()
                    elif any(s[0] in BLOCKS for s in stack[i:]):
                        break  # an inline end tag doesn't close blocks
                    del stack[i:]
                    break
            continue
        if name in VOID:
            if name in ("br", "hr"):
                put(" ")
            continue
        if name in BLOCKS or name in RULED:
            flush()
            depth = 0
        if name in RAW:
            end = re.compile(rf"</{re.escape(name)}\b[^>]*>?", re.I).search(page, at)
            at = end.end() if end else len(page)
            continue
        if name in BLOCKS:
            for i in range(len(stack) - 1, 0, -1):
                if stack[i][0] in _CLOSES.get(name, ()):
                    del stack[i:]
                    break
                if stack[i][0] in BLOCKS:
                    break
        marks = " ".join(a or b or c for _, a, b, c in _ATTRIBUTE.findall(m[3])) if "=" in m[3] else ""
        _, path, kinds, ruled = stack[-1]
        kind = kind_of(name, marks, "c" in kinds)
        own = name in RULED or bool(marks and name not in ("html", "body", *CONTENT) and COMMENTS.search(marks))
        if kind == "n" or own and not ruled:
            flush()
        if name in BLOCKS or kind == "n" or own:
            path = f"{path}/{name}" + (f".{re.sub(r'[./ ]+', '.', _SPACE.sub(' ', marks).strip())}" if marks else "")
            kinds += kind
        if m[3].rstrip().endswith("/") and name not in BLOCKS:
            continue
        depth += name == "a"
        stack.append((name, path, kinds, ruled or own))
    flush()
    return out


def hash_of(text: str) -> int:
    return xxhash.xxh3_64_intdigest(text.encode("utf-8", "surrogatepass")) - (1 << 63)


def prefixes(path: str) -> list[str]:
    """The path and its ancestors, from the root down."""
    at = [i for i, c in enumerate(path) if c == "/"][1:]
    return [path[:i] for i in at] + [path] if path else []


def nodes_of(found: list[tuple[str, str, str, int]]) -> list[tuple]:
    """(path, kind, layout, text, share, link share, whole) of each node of a page's blocks."""
    total = sum(len(t) for _, _, t, _ in found)
    whole = hash_of("\n".join(t for _, k, t, _ in found if "n" not in k))
    nodes: dict[str, list] = {}
    for path, kinds, text, links in found:
        for p, k in zip(prefixes(path), kinds, strict=True):
            own = nodes.setdefault(p, [k, [], [], 0])
            own[1].append(path[len(p) :])
            own[2].append(text)
            own[3] += links
    out = []
    for p, (k, paths, texts, links) in nodes.items():
        size = sum(map(len, texts))
        out.append((p, k, hash_of("\n".join(paths)), hash_of("\n".join(texts)), size / total, links / size, whole))
    return out


def statistics(pages: DataFrame) -> DataFrame:
    """host, path, kind, pages, presentation, content, share, link of every node; pages of equal text are one."""

    def run(batches: Iterator[pd.DataFrame]) -> Iterator[pd.DataFrame]:
        for b in batches:
            rows = [(host_of(url), *n) for url, page in zip(b["url"], b["html"], strict=True) for n in nodes_of(blocks(page or ""))]
            yield pd.DataFrame(rows, columns=["host", "path", "kind", "layout", "text", "share", "link", "whole"])

    seen = pages.select("url", "html").mapInPandas(run, "host string, path string, kind string, layout long, text long, share double, link double, whole long")
    once = seen.groupBy("host", "path", "kind", "layout", "text", "whole").agg(F.max("share").alias("share"), F.max("link").alias("link"))
    texts = once.groupBy("host", "path", "kind", "text", "layout").agg(F.count(F.lit(1)).alias("c"), F.sum("share").alias("share"), F.sum("link").alias("link"))
    logs = lambda c: F.sum(F.col(c) * F.log(c))
    by_text = texts.groupBy("host", "path", "kind", "text").agg(F.sum("c").alias("c")).groupBy("host", "path", "kind").agg(logs("c").alias("t"))
    by_layout = texts.groupBy("host", "path", "kind", "layout").agg(*(F.sum(x).alias(x) for x in ("c", "share", "link")))
    nodes = by_layout.groupBy("host", "path", "kind").agg(F.sum("c").alias("pages"), logs("c").alias("l"), F.sum("share").alias("share"), F.sum("link").alias("link")).join(by_text, ["host", "path", "kind"])
    entropy = lambda s: F.when(F.col("pages") > 1, F.greatest(F.lit(0.0), F.lit(1.0) - F.col(s) / (F.col("pages") * F.log("pages")))).otherwise(1.0)
    return nodes.select("host", "path", "kind", "pages", entropy("l").alias("presentation"), entropy("t").alias("content"), (F.col("share") / F.col("pages")).alias("share"), (F.col("link") / F.col("pages")).alias("link"))


def importances(nodes: DataFrame, prior_pages: float = PRIOR_PAGES) -> DataFrame:
    """The nodes with their importance: what they show, and the prior, both from the root down."""
    up = F.expr("transform(sequence(2, size(split(path, '/'))), i -> array_join(slice(split(path, '/'), 1, i), '/'))")
    chain = nodes.select("host", "path", "kind", F.posexplode(up).alias("at", "above"))
    own = nodes.select("host", F.col("path").alias("above"), F.col("kind").alias("k"), "pages", "presentation", "content", "share", "link")
    # a path has one kind, but for header elements: of several, the first counts
    own = own.groupBy("host", "above").agg(F.max_by(F.struct("k", "pages", "presentation", "content", "share", "link"), F.struct("pages", "k")).alias("s")).select("host", "above", "s.*")
    met = chain.join(own, ["host", "above"]).groupBy("host", "path", "kind").agg(F.sort_array(F.collect_list(F.struct("at", "k", "pages", "presentation", "content", "share", "link"))).alias("chain"))
    support = "CASE WHEN x.k = 'f' THEN a.shown * (1 - x.link) ELSE 0D END"
    shown = f"x.content * greatest(x.presentation, x.share, {support})"
    prior = "CASE x.k WHEN 'n' THEN -1D WHEN 'c' THEN 1D ELSE a.prior END"
    fold = f"aggregate(chain, named_struct('shown', 0D, 'prior', 0.5D), (a, x) -> named_struct('shown', {shown}, 'prior', {prior}))"
    w = F.lit(float(prior_pages)) / (F.lit(float(prior_pages)) + F.col("pages"))
    return nodes.join(met.select("host", "path", "kind", F.expr(fold).alias("f")), ["host", "path", "kind"]).select(*nodes.columns, ((F.lit(1.0) - w) * F.col("f.shown") + w * F.col("f.prior")).alias("importance"))


def extract(pages: DataFrame, importance: float = IMPORTANCE, prior_pages: float = PRIOR_PAGES) -> DataFrame:
    """page_id, url, text, n_chars of every page."""
    nodes = materialise(importances(materialise(statistics(pages), "nodes"), prior_pages), "importances")
    low = nodes.where(F.col("importance") < importance).groupBy("host").agg(F.collect_set("path").alias("low"))
    host = F.lower(F.regexp_extract(F.coalesce("url", F.lit("")), r"^\s*(?:[a-zA-Z][\w+.-]*:)?//(?:[^/?#@]*@)?([^/?#:]*)", 1))
    size = nodes.where(F.col("importance") < importance).agg(F.sum(F.octet_length("path") + F.octet_length("host") + 32)).first()[0] or 0
    rows = pages.select("page_id", "url", "html", host.alias("host")).join(F.broadcast(low) if size <= BROADCAST_BYTES else low, "host", "left")

    def run(batches: Iterator[pd.DataFrame]) -> Iterator[pd.DataFrame]:
        for b in batches:
            texts = []
            for page, gone in zip(b["html"], b["low"], strict=True):
                gone = set(gone) if gone is not None else set()
                texts.append(" ".join(t for p, _, t, _ in blocks(page or "") if gone.isdisjoint(prefixes(p))))
            yield pd.DataFrame({"page_id": b["page_id"], "url": b["url"], "text": texts, "n_chars": list(map(len, texts))})

    return rows.select("page_id", "url", "html", "low").mapInPandas(run, "page_id long, url string, text string, n_chars long")


def html_node_importance(spark: SparkSession, sf_dir: str) -> DataFrame:
    """What the style trees know of each node of each host."""
    return importances(materialise(statistics(load(spark, sf_dir, "pages")), "nodes"))


def op8_html_text(spark: SparkSession, sf_dir: str) -> DataFrame:
    return extract(load(spark, sf_dir, "pages"))


QUERIES = {"op8_html_text": op8_html_text, "html_node_importance": html_node_importance}
SQL: dict[str, str] = {}
