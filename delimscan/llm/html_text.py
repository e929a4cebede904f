"""Main text of web pages with site template removal.

Pass one parses every page into blocks of text, each with the hashes of the element subtrees around it (tag, role,
and everything below), inside the main content too.  Spark counts, per host, the different pages that hold each
subtree.  Pass two drops blocks inside subtrees that recur on at least ``share`` of their host's pages (and on
``least`` of them), and joins the rest.

Pages count as different by their text, so copies that differ in title, comments, scripts or attributes are one page.
Where recurrence would take three quarters of a page's text or more, it is taken for the page's content and stays.
As a supplement, menus, headers, footers, sidebars, notices, adverts, forms, scripts, styles and reader comments are
left out by tag, role or class, however rare they are.

Defined results: null or empty html gives an empty text of length 0; a null url belongs to the host ''; pages that
repeat exactly count as one page towards recurrence, and each gives its text; unclosed, stray and misnested tags are
repaired much as browsers do, and a tag that the page does not finish is left out with what follows; pages of any
length or depth take time in proportion to it; an empty table gives no row; other columns do not matter, whatever
their names.
"""

from __future__ import annotations

import html
import re
from collections import Counter
from collections.abc import Iterator
from urllib.parse import urlsplit

import pyarrow as pa
import xxhash
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from .common import durable

# possessive throughout, so a page takes time in proportion to its length; a quote opens a value only behind "="
COMMENT = re.compile(r"<!--(?:-?>|.*?(?:--!?>|\Z))", re.S)
TAG = re.compile(r"<(/?)([a-zA-Z][^\s/>]*+)((?:[^>=]++|=\s*+(?:\"[^\"]*+\"|'[^']*+'|[^\s\"'>][^\s>]*+)?+)*+)>")
ATTR = re.compile(r"([^\s=/>]++)(?:\s*+=\s*+(?:\"([^\"]*+)\"|'([^']*+)'|([^\s>\"'][^\s>]*+)))?+")
# Element names of the HTML standard, by the part they play here.
VOID = frozenset("area base br col embed hr img input link meta param source track wbr".split())
RAW = frozenset("script style textarea title noscript iframe template xmp noembed noframes".split())
DROP = frozenset("script style textarea title noscript iframe template xmp noembed noframes head nav footer aside form button select option fieldset dialog menu svg canvas object audio video datalist input label".split())
BLOCK = frozenset("address article aside blockquote body center details dd dialog dir div dl dt fieldset figcaption figure footer form h1 h2 h3 h4 h5 h6 header hgroup hr html legend li main menu nav ol p pre search section summary table tbody td tfoot th thead tr ul caption".split())
CLOSES_P = BLOCK - {"body", "html", "td", "th", "tr", "tbody", "thead", "tfoot", "caption", "legend"}
SCOPE = frozenset("html table td th caption template button object".split())
IMPLIED = {"li": ({"li"}, {"ul", "ol", "menu"}), "dt": ({"dt", "dd"}, {"dl"}), "dd": ({"dt", "dd"}, {"dl"}), "tr": ({"tr", "td", "th"}, {"table"}), "td": ({"td", "th"}, {"tr", "table"}), "th": ({"td", "th"}, {"tr", "table"}), "option": ({"option"}, {"select", "datalist"})}
ROLES = frozenset("navigation banner contentinfo complementary search form dialog alertdialog alert menu menubar toolbar tablist".split())
WORDS = re.compile(
    r"(?:^|[\s_-])(?:ads?|advert\w*|adsense|sponsor\w*|promo\w*|banner|nav|navbar|navigation|menu|breadcrumbs?|sidebar|side-bar|widget|footer|masthead|site-header|page-header|topbar|cookies?|consent|gdpr|notice|notification|popup|modal|overlay|newsletter|subscribe|signup|sign-up|login|share|sharing|social|comments?|comment-list|commentlist|disqus|replies|respond|related|recommended|skip-link)(?:$|[\s_-])", re.I)
MAIN = frozenset(("article", "main"))
SPACE = re.compile(r"\s+")


class _Node:
    __slots__ = ("drop", "first", "hash", "main", "tag")

    def __init__(self, tag: str, label: str, drop: bool, main: bool, first: int):
        self.tag, self.drop, self.main, self.first = tag, drop, main, first
        self.hash = xxhash.xxh64(label)


def _boilerplate(tag: str, attrs: str, in_main: bool) -> tuple[bool, bool, str]:
    """``(drop, main, label)`` of an element."""
    got = {}
    if attrs and not attrs.isspace():
        for m in ATTR.finditer(attrs):
            got.setdefault(m[1].lower(), html.unescape(m[2] or m[3] or m[4] or ""))
    role = got.get("role", "").strip().lower()
    marks = f"{got.get('class', '')} {got.get('id', '')}".strip()
    main = tag in MAIN or role == "main"
    drop = tag in DROP or role in ROLES or "hidden" in got or got.get("aria-hidden") == "true" or (tag not in ("html", "body") and not main and bool(marks) and bool(WORDS.search(marks)))
    if tag == "header" and not in_main:
        drop = True
    if tag == "article" and in_main and marks and WORDS.search(marks):
        drop = True  # reader comments are often articles inside the article
    return drop, main, f"{tag}\x00{role}\x00{marks}"


Tree = tuple[int, int, int]  # hash of a subtree, its first block, the block behind its last


def blocks_of(page: str) -> tuple[list[tuple[str, bool]], list[Tree]]:
    """``(blocks, subtrees)``: each block's text and whether its markup rules it out, and the subtrees with blocks in them."""
    stack: list[_Node] = []
    blocks: list[tuple[str, bool]] = []
    trees: list[Tree] = []
    opened: Counter[str] = Counter()  # open elements by tag, so what is not open is not looked for
    text: list[str] = []
    drops, mains, pos, n = 0, 0, 0, len(page)
    low = None

    def flush() -> None:
        if text:
            joined = SPACE.sub(" ", "".join(text)).strip()
            text.clear()
            if joined:
                blocks.append((joined, drops > 0))

    def close(k: int) -> None:
        """End every element from depth k on."""
        nonlocal drops, mains
        while len(stack) > k:
            node = stack[-1]
            if node.tag in BLOCK:
                flush()
            stack.pop()
            opened[node.tag] -= 1
            drops, mains = drops - node.drop, mains - node.main
            value = node.hash.intdigest()
            if node.first < len(blocks) and node.tag not in ("html", "body"):
                trees.append((value - (1 << 64) if value >> 63 else value, node.first, len(blocks)))
            if stack:
                stack[-1].hash.update(value.to_bytes(8, "little"))

    def add(raw: str) -> None:
        if raw:
            words = html.unescape(raw) if "&" in raw else raw
            text.append(words)
            if stack:
                stack[-1].hash.update(SPACE.sub(" ", words).strip().encode("utf-8", "surrogatepass"))

    def find(names: set[str], stop: frozenset[str] | set[str]) -> int:
        if any(opened[x] for x in names):
            for i in range(len(stack) - 1, -1, -1):
                if stack[i].tag in names:
                    return i
                if stack[i].tag in stop:
                    break
        return -1

    while pos < n:
        at = page.find("<", pos)
        if at < 0:
            add(page[pos:])
            break
        after = page[at + 1 : at + 3]
        if not after or not (after[0] in "!?" or after[0].isascii() and after[0].isalpha() or after[0] == "/" and len(after) > 1):
            add(page[pos : at + 1])  # a sign, not a tag
            pos = at + 1
            continue
        add(page[pos:at])
        m = TAG.match(page, at)
        if m is None:
            if page.startswith("<!--", at):
                pos = COMMENT.match(page, at).end()
            else:  # a declaration, or a tag that the page does not finish
                end = page.find(">", at)
                pos = n if end < 0 or after[0].isalpha() else end + 1
            continue
        pos = m.end()
        tag = m[2].lower()
        if m[1]:
            if tag == "br":
                text.append(" ")
            elif (k := find({tag}, frozenset() if tag in BLOCK else SCOPE)) >= 0:
                close(k)
            continue
        if tag == "br":
            text.append(" ")
            continue
        if tag in CLOSES_P and (k := find({"p"}, SCOPE)) >= 0:
            close(k)
        if tag in IMPLIED and (k := find(*IMPLIED[tag])) >= 0:
            close(k)
        if tag in BLOCK:
            flush()
        if tag in VOID:
            continue
        drop, main, label = _boilerplate(tag, m[3], mains > 0)
        stack.append(_Node(tag, label, drop, main, len(blocks)))
        opened[tag] += 1
        drops, mains = drops + drop, mains + main
        if tag in RAW:
            if low is None:
                low = page.lower() if len(page.lower()) == n else re.sub("[A-Z]", lambda c: c[0].lower(), page)
            end = low.find(f"</{tag}", pos)
            pos = n if end < 0 else end
            if m[3].rstrip().endswith("/") and tag not in ("script", "style", "title", "textarea"):
                pos = m.end()
            if pos > m.end():
                stack[-1].hash.update(page[m.end() : pos].encode("utf-8", "surrogatepass"))
    flush()
    close(0)
    return blocks, trees


def host_of(url: str | None) -> str:
    try:
        return (urlsplit(url or "").hostname or "").rstrip(".")
    except ValueError:
        return ""


def parse_pages(pages: DataFrame, id_col: str = "page_id", url_col: str = "url", html_col: str = "html") -> DataFrame:
    """``(uid, page_id, url, host, content, trees, blocks)``; ``content`` identifies pages of equal text, ``uid`` rows."""
    block = pa.list_(pa.struct([("text", pa.string()), ("ruled", pa.bool_())]))
    tree = pa.list_(pa.struct([("node", pa.int64()), ("first", pa.int32()), ("stop", pa.int32())]))

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        from pyspark import TaskContext

        uid = TaskContext.get().partitionId() << 33
        for batch in batches:
            for lo in range(0, batch.num_rows, 128):
                rows = batch.slice(lo, 128)
                got = [blocks_of(h or "") for h in rows.column(2).to_pylist()]
                cols = [
                    pa.array(range(uid, uid + rows.num_rows), pa.int64()), rows.column(0), rows.column(1),
                    pa.array([host_of(u) for u in rows.column(1).to_pylist()], pa.string()),
                    pa.array([int.from_bytes(xxhash.xxh64_digest("\n".join(t for t, ruled in b if not ruled).encode("utf-8", "surrogatepass")), "little", signed=True) for b, _ in got], pa.int64()),
                    pa.array([[{"node": h, "first": i, "stop": j} for h, i, j in x] for _, x in got], tree),
                    pa.array([[{"text": t, "ruled": r} for t, r in b] for b, _ in got], block),
                ]
                uid += rows.num_rows
                yield pa.RecordBatch.from_arrays(cols, ["uid", "page_id", "url", "host", "content", "trees", "blocks"])

    src = pages.select(F.col(id_col).cast("long").alias("page_id"), F.col(url_col).cast("string").alias("url"), F.col(html_col).cast("string").alias("html"))
    return src.mapInArrow(run, "uid long, page_id long, url string, host string, content long, trees array<struct<node: long, first: int, stop: int>>, blocks array<struct<text: string, ruled: boolean>>")


def site_templates(parsed: DataFrame, share: float = 0.5, least: int = 3) -> DataFrame:
    """``(host, node, n)`` of subtrees on at least ``share`` of the different pages of a host, and on ``least`` of them; ``n`` such pages."""
    once = parsed.select("host", "content", F.explode("trees.node").alias("node")).distinct()
    held = once.groupBy("host", "node").agg(F.count("*").alias("n")).where(F.col("n") >= least)
    pages = parsed.select("host", "content").distinct().groupBy("host").agg(F.count("*").alias("pages"))
    return held.join(pages, "host").where(F.col("n") >= share * F.col("pages")).select("host", "node", "n")


def judged(pages: DataFrame, share: float = 0.5, least: int = 3, broadcast_rows: int = 100_000, heavy_pages: int = 65_536, id_col: str = "page_id", url_col: str = "url", html_col: str = "html") -> DataFrame:
    """Parsed pages with ``gone``, the blocks ``(first, stop)`` of the recurring subtrees of each (null if none)."""
    parsed = durable(parse_pages(pages, id_col, url_col, html_col))
    found = durable(site_templates(parsed, share, least))
    nodes = parsed.select("uid", "host", F.explode("trees").alias("t")).select("uid", "host", "t.node", "t.first", "t.stop")
    names = found.select("host", "node")
    if found.count() <= broadcast_rows:
        near = nodes.join(F.broadcast(names), ["host", "node"], "left_semi")
    else:  # templates on very many pages are few, one at most for so many subtrees, and met without a shuffle; the rest have no hot key
        heavy, light = (F.broadcast(found.where(F.col("n") > heavy_pages).select("host", "node")), found.where(F.col("n") <= heavy_pages).select("host", "node"))
        near = nodes.join(heavy, ["host", "node"], "left_semi").unionByName(nodes.join(heavy, ["host", "node"], "left_anti").join(light, ["host", "node"], "left_semi"))
    hits = durable(near.groupBy("uid").agg(F.collect_set(F.struct("first", "stop")).alias("gone")))
    spans = hits.agg(F.sum(F.size("gone"))).first()[0] or 0  # eight bytes each
    side = F.broadcast(hits) if spans <= broadcast_rows else hits  # above that size the join shuffles
    return parsed.join(side, "uid", "left")


def extract_text(pages: DataFrame, share: float = 0.5, least: int = 3, id_col: str = "page_id", url_col: str = "url", html_col: str = "html") -> DataFrame:
    """``(page_id, url, text, n_chars)`` of every page."""
    placed = F.transform("blocks", lambda b, i: F.struct(b["text"].alias("text"), b["ruled"].alias("ruled"), i.alias("at")))
    open_ = F.filter(placed, lambda b: ~b["ruled"])
    live = F.filter(open_, lambda b: ~F.exists("gone", lambda g: (g["first"] <= b["at"]) & (b["at"] < g["stop"])))
    size = lambda c: F.aggregate(c, F.lit(0), lambda n, b: n + F.char_length(b["text"]))
    kept = F.when(F.col("gone").isNull() | (4 * size(live) <= size(open_)), open_).otherwise(live)
    text = F.coalesce(F.array_join(F.transform(kept, lambda b: b["text"]), "\n\n"), F.lit(""))
    out = judged(pages, share, least, id_col=id_col, url_col=url_col, html_col=html_col)
    return out.select(F.col("page_id").alias(id_col), F.col("url").alias(url_col), text.alias("text")).withColumn("n_chars", F.char_length("text").cast("long"))
