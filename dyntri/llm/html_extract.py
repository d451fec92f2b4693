"""Main text of HTML pages by wrapper induction.

All distinct pages of a host are parsed to trees, grouped by layout, and aligned with a reference page of their group by
simple tree matching. Text nodes that stay the same on most of them are the group's template; the others are slots that
vary. Extraction aligns each page with the pruned template of its group and leaves out what meets a constant node, as well
as elements that are no article by their kind or name (menus, forms, scripts, comments and the like).
"""

from __future__ import annotations

import html
import json
import re
from collections.abc import Iterator
from hashlib import md5
from zlib import crc32

import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from . import storage

#: Distinct pages that a group needs for a template, and the share of them on which a node is constant.
LEAST, CONSTANT = 4, 0.8
#: Elements that make a layout, down to this depth.
FRAME, DEPTH = frozenset("html body div section article main aside nav header footer form center table tbody tr td".split()), 4
#: Characters of reference pages or templates that are broadcast; more of them are joined.
SENT = 32_000_000
#: Child lists with more pairs than this are aligned by equal or like children instead of by all pairs.
PAIRS = 2500

VOID = frozenset("area base br col embed hr img input link meta param source track wbr".split())
INLINE = frozenset("a abbr acronym b bdi bdo big br cite code data del dfn em font i img ins kbd label mark q rp rt ruby s samp small span strike strong sub sup time tt u var wbr".split())
DROPPED = frozenset("script style noscript template nav aside form footer button select textarea iframe svg canvas object dialog menu head title fieldset input option video audio math".split())
RAW = re.compile(r"</(script|style|textarea|title|noscript)\s*>", re.I)
NAMES = re.compile(
    r"(?:^|[\s_-])(?:nav|navbar|navigation|menu|menubar|sidebar|side|footer|foot|masthead|topbar|header|banner|ad|ads|advert|advertisement|adbox|adsense|sponsor|sponsored|promo|cookie|cookies|consent|gdpr|notice|alert|"
    r"comment|comments|commentlist|respond|disqus|reply|replies|related|recommended|share|sharing|social|breadcrumb|breadcrumbs|newsletter|subscribe|signup|login|popup|modal|overlay|pagination|pager|widget|search|toc|skip|copyright|legal|tags)(?=$|[\s_-]|\d)",
    re.I,
)
ROLES = frozenset("navigation banner contentinfo complementary search form dialog alert menu menubar".split())
#: Start tags that end an open element of the second set.
ENDS = {
    **dict.fromkeys("p div ul ol dl table h1 h2 h3 h4 h5 h6 pre blockquote section article aside header footer nav form figure main hr address fieldset".split(), frozenset(["p"])),
    "li": frozenset(["li", "p"]), "dt": frozenset(["dt", "dd", "p"]), "dd": frozenset(["dt", "dd", "p"]), "tr": frozenset(["tr", "td", "th", "p"]), "td": frozenset(["td", "th", "p"]), "th": frozenset(["td", "th", "p"]), "option": frozenset(["option"]),
}
STOPS = frozenset("ul ol dl table td th div section article body main aside form blockquote".split())
TOKEN = re.compile(r"<!--.*?(?:-->|$)|<!\[CDATA\[.*?(?:\]\]>|$)|<[!?][^>]*>|<(/?)([a-zA-Z][^\s/>]*)((?:[^>\"']|\"[^\"]*\"|'[^']*')*)>|[^<]+|<", re.S)
ATTRIBUTE = re.compile(r"\b(class|id|role|hidden|aria-hidden)\s*=\s*(?:\"([^\"]*)\"|'([^']*)'|([^\s>\"']+))", re.I)


class Node:
    __slots__ = ("kids", "name", "role", "tag", "text")

    def __init__(self, tag: str, name: str = "", role: str = "", text: str | None = None):
        self.tag, self.name, self.role, self.text, self.kids = tag, name, role, text, []

    @property
    def label(self) -> tuple[str, str]:
        return self.tag, self.name


def parse(page: str) -> Node:
    """A tree of elements and text nodes; any input gives one. Entities stay as they are until text is put out."""
    root = Node("#root")
    stack, at, find = [root], 0, TOKEN.match
    n = len(page)
    while at < n:
        m = find(page, at)
        at = m.end()
        tag = m[2]
        if tag is None:
            token = m[0]
            if token[0] != "<" or token == "<":
                stack[-1].kids.append(Node("#text", text=token))
            elif token.startswith("<![CDATA["):
                stack[-1].kids.append(Node("#text", text=html.escape(token[9:].removesuffix("]]>"))))
            continue
        tag = tag.lower()
        if m[1]:
            for k in range(len(stack) - 1, 0, -1):
                if stack[k].tag == tag:
                    del stack[k:]
                    break
                if stack[k].tag in ("td", "th", "table") and tag not in ("tr", "table", "tbody", "thead", "tfoot", "body", "html", "div", "article", "section", "main"):
                    break
            continue
        name = role = ""
        if m[3].strip():
            found = {k.lower(): html.unescape(a or b or c) for k, a, b, c in ATTRIBUTE.findall(m[3])}
            name, role = f"{found.get('class', '')} {found.get('id', '')}".strip(), found.get("role", "").lower()
        if tag in ENDS:
            closing = ENDS[tag]
            for k in range(len(stack) - 1, 0, -1):
                if stack[k].tag in closing:
                    del stack[k:]
                    break
                if stack[k].tag in STOPS:
                    break
        node = Node(tag, name, role)
        stack[-1].kids.append(node)
        if tag in ("script", "style", "textarea", "title", "noscript") and not m[3].endswith("/"):
            for end in RAW.finditer(page, at):
                if end[1].lower() == tag:
                    at = end.end()
                    break
            else:
                at = n
        elif tag not in VOID and not m[3].endswith("/"):
            stack.append(node)
    return root


# ------------------------------------------------------------------ tree matching


def _mark(node: Node) -> tuple:
    """A label and a digest of the text below: equal nodes have equal marks."""
    return (*node.label, crc32(" ".join(_texts(node)).encode("utf-8", "surrogatepass")))


def _texts(node: Node) -> list[str]:
    if node.text is not None:
        return node.text.split()
    out, stack = [], [node]
    while stack:
        x = stack.pop()
        if x.text is not None:
            out += x.text.split()
        stack.extend(reversed(x.kids))
    return out


def matched(a: Node, b: Node, depth: int = 0) -> tuple[int, list[tuple[Node, Node]]]:
    """Simple tree matching: the size of the largest order-keeping alignment of like-labelled nodes, and its pairs."""
    if a.label != b.label or depth > 60:
        return 0, []
    x, y = a.kids, b.kids
    if not x or not y:
        return 1, [(a, b)]
    if len(x) * len(y) > PAIRS:
        return _listed(a, b, depth)
    cell = {}
    best = [[0] * (len(y) + 1) for _ in range(len(x) + 1)]
    for i, p in enumerate(x, 1):
        row, above = best[i], best[i - 1]
        for j, q in enumerate(y, 1):
            w = 0
            if p.label == q.label:
                if p.text is not None:
                    got = (2 if p.text == q.text else 1, [(p, q)])
                else:
                    got = matched(p, q, depth + 1)
                cell[i, j] = got
                w = got[0]
            row[j] = max(above[j], row[j - 1], above[j - 1] + w)
    pairs, i, j = [(a, b)], len(x), len(y)
    while i and j:
        if best[i][j] == best[i - 1][j]:
            i -= 1
        elif best[i][j] == best[i][j - 1]:
            j -= 1
        else:
            pairs += cell[i, j][1]
            i, j = i - 1, j - 1
    return best[len(x)][len(y)] + 1, pairs


def _listed(a: Node, b: Node, depth: int) -> tuple[int, list[tuple[Node, Node]]]:
    """Long lists: children with equal marks meet first, in order; between them, like labels do."""
    places: dict[tuple, list[int]] = {}
    for j, q in enumerate(b.kids):
        places.setdefault(_mark(q), []).append(j)
    anchors, least = [], 0
    for i, p in enumerate(a.kids):
        own = [j for j in places.get(_mark(p), ()) if j >= least]
        if own and _texts(p):
            anchors.append((i, own[0]))
            least = own[0] + 1
    total, pairs = 1, [(a, b)]
    i0 = j0 = 0
    for i, j in [*anchors, (len(a.kids), len(b.kids))]:
        free = list(range(j0, j))
        for k in range(i0, i):
            other = next((m for m in free if b.kids[m].label == a.kids[k].label), None)
            if other is not None:
                n, more = matched(a.kids[k], b.kids[other], depth + 1)
                total, pairs, free = total + n, pairs + more, [m for m in free if m > other]
        if i < len(a.kids):
            n, more = matched(a.kids[i], b.kids[j], depth + 1)
            total, pairs = total + n, pairs + more
        i0, j0 = i + 1, j + 1
    return total, pairs


def layout(root: Node) -> int:
    """A digest of the frame of a page: the paths of its outer elements, whatever their number; digits in names don't count."""
    paths: set[str] = set()
    stack = [(k, "", 1) for k in root.kids]
    while stack:
        node, above, depth = stack.pop()
        if node.tag not in FRAME:
            continue
        path = f"{above}/{node.tag} {re.sub('[0-9]+', '', node.name)}"
        paths.add(path)
        if depth < DEPTH:
            stack.extend((k, path, depth + 1) for k in node.kids)
    return int.from_bytes(md5("\n".join(sorted(paths)).encode("utf-8", "surrogatepass")).digest()[:7])


def _numbered(root: Node) -> dict[int, int]:
    """The numbers of the text nodes in page order, by identity."""
    out: dict[int, int] = {}
    stack = [root]
    while stack:
        node = stack.pop()
        if node.text is not None:
            out[id(node)] = len(out)
        stack.extend(reversed(node.kids))
    return out


def votes(reference: Node, numbers: dict[int, int], page: Node) -> list[int]:
    """The numbers of the reference's text nodes that the page has too."""
    return [numbers[id(p)] for p, q in matched(reference, page)[1] if p.text is not None and p.text.strip() and p.text == q.text]


def pruned(reference: Node, constant: set[int]) -> str | None:
    """The template as JSON: what the reference has of constant nodes; None if there are none."""
    numbers = _numbered(reference)

    def cut(node: Node) -> list | None:
        if node.text is not None:
            return ["#text", "", node.text] if numbers[id(node)] in constant else None
        kids = [k for k in map(cut, node.kids) if k]
        return [node.tag, node.name, kids] if kids else None

    found = cut(reference)
    return json.dumps(found) if found else None


def _template(spec: list) -> Node:
    tag, name, rest = spec
    if tag == "#text":
        return Node("#text", text=rest)
    node = Node(tag, name)
    node.kids = [_template(k) for k in rest]
    return node


# ------------------------------------------------------------------ extraction


def boilerplate(node: Node, inside: bool) -> bool:
    """Is the element no part of an article by its kind, role or name; inside: it stands in an article."""
    if node.tag in DROPPED or node.role in ROLES:
        return True
    if node.tag == "header":
        return not inside
    return bool(node.name) and node.tag not in ("html", "body", "main") and bool(NAMES.search(node.name)) and not (inside and node.tag in ("h1", "h2"))


def articles(root: Node) -> list[Node]:
    """The outermost article elements outside of boilerplate, else main elements, else the page."""
    for wanted in (lambda n: n.tag == "article", lambda n: n.tag == "main" or n.role == "main"):
        out, stack = [], [root]
        while stack:
            node = stack.pop()
            if node.text is not None or boilerplate(node, False):
                continue
            if wanted(node):
                out.append(node)
            else:
                stack.extend(reversed(node.kids))
        if out:
            return out
    return [root]


def main_text(page: str, template: Node | None = None) -> str:
    """The article's blocks in page order, joined by two newlines; white space in a block is one space.

    A template that would leave nothing of an article is not applied to it.
    """
    root = parse(page)
    constant: set[int] = set()
    if template is not None:
        constant = {id(p) for p, q in matched(root, template)[1] if p.text is not None and p.text == q.text}
    blocks: list[str] = []
    for top in articles(root):
        blocks += _blocks(top, top is not root, constant) or (_blocks(top, top is not root, set()) if constant else [])
    return "\n\n".join(blocks)


def _blocks(top: Node, inside: bool, constant: set[int]) -> list[str]:
    """The blocks of one article without its constant nodes."""
    blocks: list[str] = []
    run: list[str] = []

    def close() -> None:
        text = " ".join(html.unescape("".join(run)).split())
        if text:
            blocks.append(text)
        run.clear()

    stack: list[tuple[Node, bool]] = [(top, False)]
    while stack:
        node, done = stack.pop()
        if node.text is not None:
            if id(node) not in constant:
                run.append(node.text)
        elif done:
            close()
        elif node is not top and boilerplate(node, inside):
            if node.tag not in INLINE:
                close()
        else:
            if node.tag == "br":
                run.append(" ")
            elif node.tag not in INLINE:
                close()
                stack.append((node, True))
            stack.extend((k, False) for k in reversed(node.kids))
    close()
    return blocks


# ------------------------------------------------------------------ the operator


def host(url: str = "url"):
    """The host of a URL, lower-cased; empty where there is none."""
    return F.lower(F.regexp_extract(F.coalesce(F.col(url), F.lit("")), r"^[a-zA-Z][\w+.-]*://(?:[^/?#@]*@)?([^/?#:]*)", 1))


def _laid(pages: DataFrame) -> DataFrame:
    """page_id, url, html of all rows with host and layout."""

    def lay(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in batches:
            yield pa.RecordBatch.from_arrays([*batch.columns, pa.array([layout(parse(h or "")) for h in batch.column(2).to_pylist()], pa.int64())], [*batch.schema.names, "layout"])

    return pages.select("page_id", "url", "html", host().alias("host")).mapInArrow(lay, "page_id long, url string, html string, host string, layout long")


def _sent(df: DataFrame, column: str) -> DataFrame:
    """``df`` for a join that broadcasts it unless its texts are too long."""
    return F.broadcast(df) if (df.agg(F.sum(F.length(column))).first()[0] or 0) <= SENT else df


def wrappers(pages: DataFrame) -> tuple[DataFrame, DataFrame]:
    """(host, layout, cluster, n) of all layouts, and (host, cluster, template, size) of the groups of pages.

    A host's pages of one layout are a group; those of its layouts with fewer than LEAST distinct pages make up one more,
    cluster -1. Pages are distinct by digest. Each distinct page votes for the nodes that it shares with its group's
    reference, the page with the first digest; votes are counted by node, so a large host meets in no task.
    """
    some = pages.where("html <> ''").where(host() != "")
    keys = _laid(some).select("host", "layout", F.md5("html").alias("digest")).distinct()
    known = keys.groupBy("host", "layout").agg(F.count(F.lit(1)).alias("n"), F.min("digest").alias("digest"))
    layouts = storage.saved(known.withColumn("cluster", F.when(F.col("n") < LEAST, -1).otherwise(F.col("layout"))), "layouts")
    clusters = layouts.groupBy("host", "cluster").agg(F.sum("n").alias("size"), F.min("digest").alias("digest")).where(F.col("size") >= LEAST)
    texts = some.select(host().alias("host"), F.md5("html").alias("digest"), "html").join(clusters, ["host", "digest"])
    references = storage.saved(texts.groupBy("host", "cluster").agg(F.first("size").alias("size"), F.first("digest").alias("first"), F.first("html").alias("reference")), "references")
    rows = _laid(some).join(layouts.select("host", "layout", "cluster"), ["host", "layout"]).join(_sent(references, "reference"), ["host", "cluster"])

    def vote(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        parsed: dict[str, tuple[Node, dict[int, int]]] = {}
        for batch in batches:
            out = []
            for page, reference in zip(batch.column(3).to_pylist(), batch.column(4).to_pylist()):
                if reference not in parsed:
                    if len(parsed) > 1000:
                        parsed.clear()
                    tree = parse(reference)
                    parsed[reference] = tree, _numbered(tree)
                out.append(votes(*parsed[reference], parse(page)))
            yield pa.RecordBatch.from_arrays([*batch.columns[:3], pa.array(out, pa.list_(pa.int32()))], ["host", "cluster", "digest", "nodes"])

    cast = rows.withColumn("digest", F.md5("html")).where("digest <> first").select("host", "cluster", "digest", "html", "reference").mapInArrow(vote, "host string, cluster long, digest string, nodes array<int>")
    counted = cast.groupBy("host", "cluster", "digest").agg(F.first("nodes").alias("nodes")).select("host", "cluster", F.explode("nodes").alias("node")).groupBy("host", "cluster", "node").agg(F.count(F.lit(1)).alias("k"))
    constant = counted.join(references, ["host", "cluster"]).where(F.col("k") >= CONSTANT * (F.col("size") - 1)).groupBy("host", "cluster").agg(F.collect_list("node").alias("nodes"))

    def prune(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in batches:
            made = [pruned(parse(r), set(nodes)) for r, nodes in zip(batch.column(3).to_pylist(), batch.column(4).to_pylist())]
            yield pa.RecordBatch.from_arrays([*batch.columns[:3], pa.array(made, pa.string())], ["host", "cluster", "size", "template"])

    made = references.join(constant, ["host", "cluster"]).select("host", "cluster", "size", "reference", "nodes").mapInArrow(prune, "host string, cluster long, size long, template string")
    return layouts, storage.saved(made.where("template is not null"), "wrappers")


def extracted(pages: DataFrame) -> DataFrame:
    """page_id, url, text of every row of pages (page_id, url, html; further columns are ignored).

    A null html is empty and has an empty text; a null url, or one without a host, has no wrapper. Repeated rows give
    repeated rows; an empty table gives none. No template takes all text of an article away. A page whose group has no
    template is held against the one of its host's largest group. Templates are broadcast up to SENT characters and
    joined beyond it.
    """
    layouts, templates = wrappers(pages)
    largest = templates.groupBy("host").agg(F.max_by("template", F.struct("size", "cluster")).alias("template"))
    small = layouts.join(templates.select("host", "cluster", "template"), ["host", "cluster"], "left").join(largest.withColumnRenamed("template", "other"), "host", "left")
    known = storage.saved(small.select("host", "layout", F.coalesce("template", "other").alias("template")).where("template is not null"), "templates")
    rows = _laid(pages).join(_sent(known, "template"), ["host", "layout"], "left")

    def extract(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        parsed: dict[str, Node] = {}
        for batch in batches:
            texts = []
            for page, template in zip(batch.column(2).to_pylist(), batch.column(3).to_pylist()):
                if template and template not in parsed:
                    if len(parsed) > 1000:
                        parsed.clear()
                    parsed[template] = _template(json.loads(template))
                texts.append(main_text(page or "", parsed.get(template)))
            yield pa.RecordBatch.from_arrays([batch.column(0), batch.column(1), pa.array(texts, pa.string())], ["page_id", "url", "text"])

    return rows.select("page_id", "url", "html", "template").mapInArrow(extract, "page_id long, url string, text string")
