"""Main text of web pages, with a site style tree for each host.

The pages of a host are merged into one tree: a node is the path of tags and classes from the root, equal siblings falling
together. Two entropies say how much a node varies between the m pages that have it. A node without text of its own has the
entropy of its presentations (sequences of children), -sum p log_m p. A node with text has 1 - mean_i H(i) over its distinct
texts i, where H(i) = log_m(n_i) for a text on n_i of the pages: 0 for a text that all pages share, 1 for texts of one page.
A branch is as important as the most important node in it; unimportant branches are cut from every page.

How little importance is too little depends on what the markup says beforehand (the prior): a branch inside an article or
main element goes under main_threshold, any other under threshold, and one whose tag, role or class names its presentation
(menus, forms, adverts, comments, ...) always, as adverts and comments vary like articles do. So the entropies decide on
all that has no telling name, inside articles too; hosts of fewer than min_pages pages have the prior alone. Where article
or main elements hold text, the result is what is left inside them.

A page is parsed once, into its blocks and presentations, which are written to the shared folder; all counts are aggregates
keyed by host, node and text, so that a host with a third of all pages is no single group. The unimportant branches go back
to the pages by a broadcast while they are few (counted first), else by a join on the host.

Edge cases. A null or empty page gives an empty text; a null URL is the host "". If the tree would cut all the text of a
page, it cuts nothing there (a host of equal pages). Broken markup is closed as browsers do; very long pages are parsed
whole. Repeated rows each count and give equal texts; nodes of equal importance are treated alike. The input's html column,
and columns named text, host or noise, are replaced or dropped; others stay. An empty table gives no rows.
"""

from __future__ import annotations

import re
from dataclasses import dataclass
from html import unescape

import pyarrow as pa
from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

from softdep.llm._store import bounded_batches, written
from softdep.llm.urls import host_of

# Fixed values of HTML.
VOID = frozenset("area base br col embed hr img input link meta param source track wbr".split())
RAW = ("script", "style", "noscript", "template", "textarea", "iframe", "svg", "object", "select", "title")
INLINE = frozenset("a abbr acronym b bdi bdo big br cite code data del dfn em font i img ins kbd label mark q s samp small span strike strong sub sup time tt u var wbr".split())
CLOSES_P = frozenset("address article aside blockquote center details dialog dir div dl fieldset figcaption figure footer form h1 h2 h3 h4 h5 h6 header hgroup hr main menu nav ol p pre search section summary table ul".split())

#: Presentations that are never main text.
NOISE_TAGS = frozenset("nav footer aside form menu button dialog search head fieldset".split())
NOISE_ROLES = frozenset("navigation banner contentinfo search complementary alert alertdialog dialog menu menubar toolbar form".split())
NOISE_NAMES = frozenset(
    "ad ads adbox adslot advert adverts advertisement advertising sponsor sponsored promo promotion banner sidebar menu nav navbar navigation breadcrumb breadcrumbs footer "
    "cookie cookies consent gdpr notice notices alert popup modal overlay newsletter subscribe subscription signup login share sharing social related recommended "
    "comment comments commentlist respond disqus discussion reply replies pagination pager widget masthead topbar toolbar copyright skip skiplink".split()
)

_TOKEN = re.compile(r"<!--.*?(?:-->|$)|<!\[CDATA\[.*?\]\]>|<[!?][^>]*>|<(" + "|".join(RAW) + r")\b(?:\"[^\"]*\"|'[^']*'|[^'\">])*>.*?(?:</\1\s*>|$)|<(/?)([a-zA-Z][a-zA-Z0-9:_-]*)((?:\"[^\"]*\"|'[^']*'|[^'\">])*)>", re.S | re.I)
_ATTR = re.compile(r"([a-zA-Z-]+)\s*=\s*(?:\"([^\"]*)\"|'([^']*)'|([^\s\"'>]+))")


@dataclass(slots=True)
class _Node:
    tag: str
    path: str
    noise: bool
    main: bool
    header: bool
    children: list[str]


@dataclass(slots=True)
class Block:
    path: str
    text: str
    noise: bool
    main: bool


def _open(tag: str, attrs: str, parent: _Node) -> _Node:
    label, noise, main = tag, tag in NOISE_TAGS, parent.main or tag in ("article", "main")
    header = tag == "header" or (parent.header and tag not in ("article", "main"))
    if attrs and "=" in attrs:
        a = {m[1].lower(): m[2] or m[3] or m[4] or "" for m in _ATTR.finditer(attrs)}
        names = sorted(set(re.sub(r"\d+", "0", f"{a.get('class', '')}").lower().split()))
        if names:
            label += "." + ".".join(names)
        if tag not in ("html", "body", "article", "main"):
            noise |= not NOISE_NAMES.isdisjoint(re.split(r"[^a-z]+", f"{a.get('class', '')} {a.get('id', '')}".lower()))
        elif tag in ("article", "main"):
            noise |= not {"comment", "comments", "ad", "advert", "sponsored", "related"}.isdisjoint(re.split(r"[^a-z]+", f"{a.get('class', '')} {a.get('id', '')}".lower()))
        noise |= a.get("role", "").lower() in NOISE_ROLES or bool(re.search(r"display\s*:\s*none", a.get("style", ""))) or a.get("aria-hidden") == "true"
    if attrs and re.search(r"(?:^|\s)hidden(?:\s|=|/|$)", attrs):
        noise = True
    return _Node(tag, f"{parent.path}/{label}", parent.noise or noise, main, header, [])


def parsed(html: str | None) -> tuple[list[Block], list[tuple[str, str]]]:
    """The text blocks in page order, and (path, presentation) of each element that holds blocks."""
    root = _Node("", "", False, False, False, [])
    stack, blocks, styles, buffer = [root], [], [], []

    def flush() -> None:
        if buffer:
            text = " ".join(unescape("".join(buffer)).split())
            buffer.clear()
            if text:
                at = next(n for n in reversed(stack) if n.tag not in INLINE)
                heading = any(re.fullmatch("h[1-6]", n.tag) for n in stack)
                blocks.append(Block(at.path, text, at.noise or stack[-1].noise or (at.header and not (at.main and heading)), at.main))

    def close(to: int) -> None:
        while len(stack) > to:
            n = stack.pop()
            if n.tag not in INLINE:
                runs = [x for i, x in enumerate(n.children) if not i or n.children[i - 1] != x]
                styles.append((n.path, ",".join(runs)))

    def close_up_to(tags: tuple[str, ...], until: frozenset[str]) -> None:
        for i in range(len(stack) - 1, 0, -1):
            if stack[i].tag in tags:
                close(i)
                return
            if stack[i].tag in until:
                return

    at = 0
    for m in _TOKEN.finditer(html or ""):
        if m.start() > at:
            buffer.append(html[at : m.start()])
        at = m.end()
        if not m[3]:
            if m[1]:
                buffer.append(" ")
            elif m[0].startswith("<![CDATA["):
                buffer.append(m[0][9:-3])
            continue
        tag, ending = m[3].lower(), m[2] == "/"
        if tag in INLINE:
            if tag == "br":
                buffer.append(" ")
            elif ending:
                k = next((i for i in range(len(stack) - 1, 0, -1) if stack[i].tag == tag or stack[i].tag not in INLINE), 0)
                if k and stack[k].tag == tag:
                    if any(n.noise for n in stack[k:]) and not stack[k - 1].noise:
                        flush()
                    close(k)
            elif tag not in VOID:
                n = _open(tag, m[4], stack[-1])
                if n.noise and not stack[-1].noise:
                    flush()
                stack.append(n)
            continue
        flush()
        if ending:
            k = next((i for i in range(len(stack) - 1, 0, -1) if stack[i].tag == tag), 0)
            if k:
                close(k)
            continue
        if tag in CLOSES_P:
            close_up_to(("p",), frozenset(("td", "th", "table", "button", "object")))
        if tag == "li":
            close_up_to(("li",), frozenset(("ul", "ol", "menu")))
        elif tag in ("dt", "dd"):
            close_up_to(("dt", "dd"), frozenset(("dl",)))
        elif tag in ("td", "th"):
            close_up_to(("td", "th"), frozenset(("tr", "table")))
        elif tag == "tr":
            close_up_to(("tr",), frozenset(("table",)))
        elif tag == "option":
            close_up_to(("option",), frozenset(("select",)))
        n = _open(tag, m[4], stack[-1])
        stack[-1].children.append(n.path.rpartition("/")[2])
        if tag not in VOID:
            stack.append(n)
    if html and at < len(html):
        buffer.append(html[at:])
    flush()
    close(1)
    return blocks, styles


_PARSED = pa.struct([
    ("blocks", pa.list_(pa.struct([("path", pa.string()), ("text", pa.string()), ("noise", pa.bool_()), ("main", pa.bool_())]))),
    ("styles", pa.list_(pa.struct([("path", pa.string()), ("look", pa.string())]))),
])


_PARSED_DDL = "struct<blocks: array<struct<path: string, text: string, noise: boolean, main: boolean>>, styles: array<struct<path: string, look: string>>>"


def page_trees(pages: DataFrame, url: str = "url", html: str = "html") -> DataFrame:
    """pages without html, with host, blocks (path, text, noise, main) in page order and styles (path, look), as a written
    table: nothing is parsed twice."""
    bounded_batches(pages.sparkSession)

    @F.arrow_udf(_PARSED_DDL)
    def parse(column: pa.Array) -> pa.Array:
        out = []
        for page in column.to_pylist():
            blocks, styles = parsed(page)
            out.append({"blocks": [{"path": b.path, "text": b.text, "noise": b.noise, "main": b.main} for b in blocks], "styles": [{"path": p, "look": s} for p, s in set(styles)]})
        return pa.array(out, _PARSED)

    base = pages.drop("noise", "host", "text").withColumn("host", host_of(F.col(url))).withColumn("__p", parse(F.col(html).cast("string")))
    return written(base.drop(html).select("*", "__p.blocks", "__p.styles").drop("__p"), "trees")


def node_importance(trees: DataFrame, decay: float = 0.9) -> DataFrame:
    """(host, path, pages, importance, branch) of each node of the site style trees; branch is the most important node's
    importance in the branch. A node without text weighs 1 - decay^presentations of its entropy."""
    texts = F.transform("blocks", lambda b: F.struct(b["path"].alias("path"), F.lit(True).alias("is_text"), F.xxhash64(b["text"]).alias("feature")))
    styles = F.transform("styles", lambda s: F.struct(s["path"].alias("path"), F.lit(False).alias("is_text"), F.xxhash64(s["look"]).alias("feature")))
    each = trees.select("host", F.explode(F.array_distinct(F.concat(texts, styles))).alias("x"))
    seen = each.select("host", "x.*").groupBy("host", "path", "is_text", "feature").agg(F.count("*").alias("n"))
    # Pages that have the node: each page that has it gives one presentation.
    node = seen.groupBy("host", "path").agg(
        F.sum(F.when(~F.col("is_text"), F.col("n"))).alias("pages"),
        F.sum(F.when(~F.col("is_text"), F.col("n") * F.log("n"))).alias("s_log"),
        F.sum(F.when(~F.col("is_text"), F.lit(1))).alias("styles"),
        F.sum(F.when(F.col("is_text"), F.log("n"))).alias("t_log"),
        F.sum(F.when(F.col("is_text"), F.lit(1))).alias("texts"),
    )
    m = F.greatest(F.coalesce("pages", F.lit(1)), F.lit(1))
    log_m = F.log(m)
    style = (log_m - F.coalesce("s_log", F.lit(0.0)) / m) / log_m * (1 - F.pow(F.lit(decay), F.coalesce("styles", F.lit(0))))
    text = 1 - F.col("t_log") / F.col("texts") / log_m
    own = written(node.select("host", "path", m.alias("pages"), F.when(m == 1, 1.0).when(F.col("texts") > 0, F.greatest(text, F.lit(0.0))).otherwise(style).alias("importance")), "nodes")
    # A path /a/b/c lies in the branches /a, /a/b and /a/b/c.
    steps = F.split("path", "/")
    prefixes = F.transform(F.sequence(F.lit(2), F.greatest(F.size(steps), F.lit(2))), lambda k: F.array_join(F.slice(steps, 1, k), "/"))
    branch = own.where("path != ''").select("host", "importance", F.explode(prefixes).alias("path")).groupBy("host", "path").agg(F.max("importance").alias("branch"))
    return own.join(branch, ["host", "path"])


def noise_nodes(importance: DataFrame, threshold: float = 0.4, main_threshold: float = 0.1, min_pages: int = 5) -> DataFrame:
    """(host, noise): the paths of the host's unimportant branches, inside article and main elements by a threshold of their
    own. These elements themselves, whatever is in them, are no such branches."""
    inside = F.col("path").rlike(r"/(article|main)(\.[^/]*)?/")
    itself = F.col("path").rlike(r"/(article|main)(\.[^/]*)?$")
    low = importance.where((F.col("pages") >= min_pages) & (F.col("branch") < F.when(inside, main_threshold).otherwise(threshold)) & ~itself)
    return low.groupBy("host").agg(F.array_sort(F.collect_set("path")).alias("noise"))


def main_text(html: str | None, noise: frozenset[str] = frozenset()) -> str:
    """The page's main text: blocks joined by two line feeds."""
    blocks, _ = parsed(html)
    plain = [b for b in blocks if not b.noise]

    def cut(path: str) -> bool:
        steps = path.split("/")
        return any("/".join(steps[:k]) in noise for k in range(2, len(steps) + 1))

    kept = [b for b in plain if not cut(b.path)] if noise else plain
    kept = kept or plain
    inside = [b for b in kept if b.main]
    return "\n\n".join(b.text for b in inside or kept)


def extracted(pages: DataFrame, url: str = "url", html: str = "html", max_broadcast_rows: int = 20_000, **options: float) -> DataFrame:
    """pages with a column text in place of html; options are those of noise_nodes."""
    trees = page_trees(pages, url, html)
    noise = written(noise_nodes(node_importance(trees), **options), "noise")
    few = noise.agg(F.coalesce(F.sum(F.size("noise")), F.lit(0))).first()[0] <= max_broadcast_rows
    joined = trees.join(F.broadcast(noise) if few else noise, "host", "left")
    cut = lambda b: F.exists(F.coalesce("noise", F.array().cast("array<string>")), lambda n: (b["path"] == n) | F.startswith(b["path"], F.concat(n, F.lit("/"))))
    plain = joined.withColumn("__plain", F.filter("blocks", lambda b: ~b["noise"]))
    left = plain.withColumn("__left", F.filter("__plain", lambda b: ~cut(b))).withColumn("__left", F.when(F.size("__left") > 0, F.col("__left")).otherwise(F.col("__plain")))
    inside = left.withColumn("__main", F.filter("__left", lambda b: b["main"]))
    best = F.when(F.size("__main") > 0, F.col("__main")).otherwise(F.col("__left"))
    return inside.withColumn("text", F.array_join(F.transform(best, lambda b: b["text"]), "\n\n")).drop("host", "noise", "blocks", "styles", "__plain", "__left", "__main")


def n_chars(text: Column) -> Column:
    return F.length(text).cast("long")
