"""Main-text extraction with a site style tree.

The trees of a host's distinct pages (copies count once) are merged by path (tags with their class; an id
is often a page's own, so it is left out).  A merged node has
a presentation importance (entropy of the tag sequences of its children over the host's pages, in
units of log of their number) and a content importance (1 minus the mean entropy of its text
features over those pages: a text that all pages share has entropy 1); its importance is
``(1 - DECAY) * presentation + DECAY * content``, where its content holds that of all nodes below.
Branches of importance under ``threshold`` are removed from every page of the host, once
``min_pages`` pages have the node.  Whatever the host, elements whose tag, role, class or id says
that they are menus, headers, footers, sidebars, notices, adverts, forms, scripts, styles or reader
comments are removed, and ``article`` or ``main`` elements, where a page has one, bound its text and are
never removed themselves.

Statistics are counts by merged node and feature, summed in each task before the shuffle; pages
meet the list of their host's removed nodes through a salted key, so a host with a third of all
pages is spread over ``SALTS`` groups.

Defined cases: null and empty pages have empty text; a null url is a host of its own name ""; text
outside any element counts as the body's; unclosed and stray tags are repaired as browsers do in
the common cases; equal rows get equal texts.
"""

from __future__ import annotations

import html
import re
from collections.abc import Iterator

import numpy as np
import pyarrow as pa
from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

from .kernel import RollingHash, signed, tidy
from .workspace import keep

DECAY = 0.9
THRESHOLD = 0.2
MIN_PAGES = 4
SALTS = 32

_TOKEN = re.compile(r"""<!--.*?(?:-->|\Z)|<(/?)([a-zA-Z][^\s/>]*)((?:[^>"']|"[^"]*"|'[^']*')*+)>|<(/?)([a-zA-Z][^\s/>]*)([^>]*)>|<[!?][^>]*>""", re.S)
_ATTR = re.compile(r"""([^\s=/>"']+)(?:\s*=\s*(?:"([^"]*)"|'([^']*)'|([^\s"'>]+)))?""")
_SPLIT = re.compile(r"[^a-z0-9]+|(?<=[a-z])(?=[0-9])")
# fixed values: element names of the HTML standard, by how they are laid out
VOID = frozenset("area base br col embed hr img input link meta param source track wbr".split())
RAW = frozenset("script style textarea title noscript iframe noembed noframes xmp".split())
INLINE = frozenset("a abbr acronym b bdi bdo big cite code data del dfn em font i img ins kbd label mark q rp rt ruby s samp small span strike strong sub sup time tt u var wbr br".split())
CLOSES_P = frozenset("address article aside blockquote details div dl fieldset figcaption figure footer form h1 h2 h3 h4 h5 h6 header hr main menu nav ol p pre section table ul".split())
NOISE_TAGS = frozenset("nav footer aside form script style noscript template button select iframe head svg canvas object dialog textarea title input option datalist noembed noframes".split())
NOISE_ROLES = frozenset("navigation banner contentinfo complementary search form dialog alert alertdialog menu menubar toolbar".split())
NOISE_WORDS = frozenset(
    "ad ads advert adverts advertisement advertisements advertising adsense adsbygoogle sponsor sponsored sponsors promo promotion "
    "cookie cookies consent gdpr notice notices alert popup modal overlay newsletter subscribe subscription paywall "
    "sidebar menu nav navbar navigation topnav subnav breadcrumb breadcrumbs footer bottom masthead topbar toolbar "
    "comment comments commentlist disqus respond reply replies responses related recommended share sharing social "
    "widget widgets pagination pager skip login signup search form banner".split()
)
OUTSIDE_WORDS = frozenset("header head top".split())
MAIN = frozenset(("article", "main"))


def _attributes(raw: str) -> dict[str, str]:
    return {m[1].lower(): m[2] or m[3] or m[4] or "" for m in _ATTR.finditer(raw)} if raw.strip(" /\n\t\r") else {}


class _Node:
    __slots__ = ("tag", "path", "noise", "main", "inline", "children")

    def __init__(self, tag: str, path: str, noise: bool, main: bool, inline: bool):
        self.tag, self.path, self.noise, self.main, self.inline = tag, path, noise, main, inline
        self.children: list[str] = []


def _noisy(tag: str, attrs: dict[str, str], inside: bool) -> bool:
    if tag in NOISE_TAGS or tag == "header" and not inside:
        return True
    if not attrs:
        return False
    if "hidden" in attrs or attrs.get("aria-hidden") == "true" or attrs.get("role", "").lower() in NOISE_ROLES:
        return True
    if re.search(r"display\s*:\s*none|visibility\s*:\s*hidden", attrs.get("style", ""), re.I):
        return True
    if tag in MAIN or tag in ("body", "html") or tag in INLINE and tag not in ("a", "span"):
        return False
    words = set(_SPLIT.split(f"{attrs.get('class', '')} {attrs.get('id', '')}".lower()))
    return bool(words & NOISE_WORDS) or not inside and bool(words & OUTSIDE_WORDS)


def blocks(page: str | None) -> tuple[list[tuple[str, tuple[str, ...], bool, bool]], list[tuple[str, str]]]:
    """The page's text blocks in order - text, paths of the containers around it (outermost first),
    whether it lies in a part removed by name, whether in the main part - and (path, child tags) of
    every container."""
    out: list[tuple[str, tuple[str, ...], bool, bool]] = []
    shapes: list[tuple[str, str]] = []
    stack: list[_Node] = []
    held: list[str] = []

    def flush() -> None:
        if held:
            text = " ".join(html.unescape("".join(held)).split())
            held.clear()
            if text:
                paths = tuple(n.path for n in stack if not n.inline)
                out.append((text, paths, any(n.noise for n in stack), any(n.main for n in stack)))

    def pop() -> None:
        n = stack.pop()
        if not n.inline:
            shapes.append((n.path, ">".join(n.children)))

    def close_to(depth: int) -> None:
        flush()
        while len(stack) > depth:
            pop()

    if not page:
        return out, shapes
    at, size = 0, len(page)
    while at < size:
        m = _TOKEN.search(page, at)
        if m is None:
            held.append(page[at:])
            break
        if m.start() > at:
            held.append(page[at : m.start()])
        at = m.end()
        tag = (m[2] or m[5] or "").lower()
        if not tag:
            continue
        if m[1] or m[4]:
            depth = next((i for i in range(len(stack) - 1, -1, -1) if stack[i].tag == tag), None)
            if depth is None:
                if tag not in INLINE:
                    flush()
            elif tag in INLINE and any(not n.inline for n in stack[depth + 1 :]):
                pass  # a mark-up end across blocks ends nothing
            elif tag in INLINE and not stack[depth].noise:
                while len(stack) > depth:
                    pop()
            else:
                close_to(depth)
            continue
        if tag in ("br", "wbr"):
            held.append(" " if tag == "br" else "")
            continue
        if tag in VOID:
            if tag == "hr":
                flush()
            continue
        attrs = _attributes(m[3] or m[6] or "")
        if tag in RAW:
            end = re.compile(rf"</{tag}\s*>", re.I).search(page, at)
            at = end.end() if end else size
            if tag not in INLINE:
                flush()
            continue
        inside = any(n.main for n in stack)
        noise = _noisy(tag, attrs, inside)
        inline = tag in INLINE
        if not inline or noise:
            flush()
        if tag in CLOSES_P:
            depth = next((i for i in range(len(stack) - 1, -1, -1) if stack[i].tag == "p"), None)
            if depth is not None and all(n.inline for n in stack[depth + 1 :]):
                close_to(depth)
        elif tag in ("li", "dt", "dd", "tr", "td", "th", "option"):
            group = {"li": ("li",), "dt": ("dt", "dd"), "dd": ("dt", "dd"), "tr": ("tr", "td", "th"), "td": ("td", "th"), "th": ("td", "th"), "option": ("option",)}[tag]
            depth = None
            for i in range(len(stack) - 1, -1, -1):
                if stack[i].tag in group:
                    depth = i
                    if tag != "tr" or stack[i].tag == "tr":
                        break
                elif stack[i].tag in ("ul", "ol", "dl", "table", "select", "tbody", "thead"):
                    break
            if depth is not None:
                close_to(depth)
        name = ".".join([tag, *sorted(_SPLIT.split(attrs.get("class", "").lower()))]) if attrs else tag
        parent = next((n for n in reversed(stack) if not n.inline), None)
        if parent and not inline and (not parent.children or parent.children[-1] != tag):
            parent.children.append(tag)
        path = name if parent is None else f"{parent.path}/{name}"
        stack.append(_Node(tag, path, noise, tag in MAIN or attrs.get("role") == "main", inline))
    close_to(0)
    return out, shapes


def main_text(page: str | None, removed: frozenset[str] | set[str] = frozenset()) -> str:
    """The page's main text, without branches whose path is in ``removed``."""
    found, _ = blocks(page)
    bounded = any(main and not noise for _, _, noise, main in found)
    kept = []
    for text, paths, noise, main in found:
        if noise or bounded and not main or removed and any(p in removed for p in paths):
            continue
        kept.append(text)
    return "\n".join(kept)


def host() -> Column:
    return F.lower(F.coalesce(F.regexp_extract("url", r"^[A-Za-z][A-Za-z0-9+.-]*://(?:[^/@?#]*@)?([^/:?#]*)", 1), F.lit("")))


def _pages(batch: pa.RecordBatch, step: int = 256) -> Iterator[pa.RecordBatch]:
    for at in range(0, batch.num_rows, step):
        yield batch.slice(at, step)


def style_tree(pages: DataFrame) -> DataFrame:
    """host, path, pages, presentation, content, importance of every merged node.

    Only containers can be removed, and of those under an article not the paragraphs and headings."""
    leaves = {"p", "h1", "h2", "h3", "h4", "h5", "h6", "article", "main", "body", "html", "li", "pre", "blockquote", "td", "th", "tr", "tbody", "table"}

    def hashed(texts: list[str]) -> np.ndarray:
        raw = [t.encode() for t in texts]
        ends = np.cumsum([len(r) for r in raw])
        return signed(RollingHash(np.frombuffer(b"".join(raw), np.uint8)).spans(np.concatenate([[0], ends[:-1]]), ends)) if raw else np.zeros(0, np.int64)

    def merge(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for whole in batches:
            for batch in _pages(whole):
                tally: dict[tuple[str, str, int, str], int] = {}
                for name, page in zip(batch.column("host").to_pylist(), batch.column("html").to_pylist()):
                    found, shapes = blocks(page)
                    own = {(name, path, 0, "") for path, _ in shapes} | {(name, path, 1, shape) for path, shape in shapes}
                    own |= {(name, path, 2, text) for text, paths, _, _ in found for path in paths}
                    for key in own:
                        if key[1].rpartition("/")[2].partition(".")[0] not in leaves:
                            tally[key] = tally.get(key, 0) + 1
                keys = list(tally)
                yield pa.RecordBatch.from_arrays(
                    [pa.array([k[0] for k in keys], pa.string()), pa.array([k[1] for k in keys], pa.string()), pa.array([k[2] for k in keys], pa.int32()), pa.array(hashed([k[3] for k in keys])), pa.array(list(tally.values()), pa.int64())],
                    ["host", "path", "kind", "feature", "n"],
                )

    distinct = pages.select(host().alias("host"), "html").distinct()  # copies of a page say nothing about what its host repeats
    rows = distinct.mapInArrow(tidy(merge), "host string, path string, kind int, feature bigint, n bigint")
    features = rows.groupBy("host", "path", "kind", "feature").agg(F.sum("n").alias("n"))
    nodes = features.groupBy("host", "path").agg(
        F.sum(F.when(F.col("kind") == 0, F.col("n")).otherwise(0)).alias("pages"),
        F.sum(F.when(F.col("kind") == 1, F.col("n") * F.log("n")).otherwise(0.0)).alias("shape_sum"),
        F.sum(F.when(F.col("kind") == 1, F.col("n")).otherwise(0)).alias("shape_n"),
        F.avg(F.when(F.col("kind") == 2, F.log("n"))).alias("text_log"),
    )
    scale = F.log(F.greatest("pages", F.lit(2)))
    presentation = F.when(F.col("pages") > 1, (F.log(F.greatest("shape_n", F.lit(1))) - F.col("shape_sum") / F.greatest("shape_n", F.lit(1))) / scale).otherwise(1.0)
    content = F.greatest(F.lit(0.0), 1 - F.coalesce(F.col("text_log"), F.lit(0.0)) / scale)
    nodes = nodes.select("host", "path", "pages", presentation.alias("presentation"), content.alias("content"))
    return nodes.withColumn("importance", (1 - DECAY) * F.col("presentation") + DECAY * F.col("content"))


def extract(pages: DataFrame, threshold: float = THRESHOLD, min_pages: int = MIN_PAGES) -> DataFrame:
    """Every row of ``pages`` with ``text`` and ``n_chars`` added (such columns are replaced)."""
    pages = pages.drop("text", "n_chars")
    low = style_tree(pages).where((F.col("importance") < threshold) & (F.col("pages") >= min_pages))
    low = keep(low.groupBy("host").agg(F.collect_set("path").alias("removed")), "style-tree")
    low = low.select("host", "removed", F.explode(F.sequence(F.lit(0), F.lit(SALTS - 1))).alias("salt"))
    names = pages.columns
    # the caller's columns travel in a struct, out of the way of those made here
    salted = pages.select(F.struct(*(F.col(f"`{c}`") for c in names)).alias("row"), host().alias("host"), F.pmod(F.xxhash64("html"), F.lit(SALTS)).cast("int").alias("salt"))
    removed = "removed"
    while removed in map(str.lower, names):
        removed += "_"
    joined = salted.join(low, ["host", "salt"], "left").select(*(F.col("row")[c].alias(c) for c in names), F.col("removed").alias(removed))

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for whole in batches:
            for batch in _pages(whole):
                texts = [main_text(p, set(r or ())) for p, r in zip(batch.column("html").to_pylist(), batch.column(removed).to_pylist())]
                yield pa.RecordBatch.from_arrays([*(batch.column(c) for c in names), pa.array(texts, pa.string()), pa.array([len(t) for t in texts], pa.int64())], [*names, "text", "n_chars"])

    kinds = ", ".join(f"`{f.name}` {f.dataType.simpleString()}" for f in pages.schema)
    return joined.mapInArrow(tidy(run), f"{kinds}, text string, n_chars bigint")
