"""HTML extraction by wrapper induction.

Pages of one host are aligned as trees by simple tree matching. A node that has the same text on all pages is
template; nodes whose text varies are slots that hold content. Wrappers are folded page by page inside each
task and merged per host afterwards, so no task ever holds the pages of a host. What elements, roles and
class names say about menus, adverts, forms and the like is respected first. Inside an explicit article or main
element the wrapper decides as well; since copied articles are alike too, pages of a host with the same text count
once, and there a constant node must be shared by most pages that have such an element.
"""

from __future__ import annotations

import html as entities
import json
import re
from collections import Counter
from collections.abc import Iterator
from hashlib import blake2b

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from .common import materialize
from .url_filter import split

TOKEN = re.compile(r"""<!--.*?(?:-->|\Z)|<(/?)([a-zA-Z][^\s/<>]*)((?:[^<>"']++|"[^"]*"|'[^']*')*+)(?:>|(?=<)|\Z)|<[!?/][^<>]*+>?""", re.S)
ATTRIBUTE = re.compile(r"""([^\s=/"'>]+)(?:\s*=\s*("[^"]*"|'[^']*'|[^\s>"']+))?""")
#: Words inside class names and ids, split at signs and at capitals.
NAME = re.compile(r"[A-Z]?[a-z]+|[A-Z]+|\d+")
VOID = frozenset("area base br col embed hr img input link meta param source track wbr".split())
RAW = frozenset("script style textarea title noscript iframe noembed noframes xmp".split())
INLINE = frozenset("a abbr acronym b bdi bdo big cite code data del dfn em font i ins kbd label mark q rp rt ruby s samp small span strike strong sub sup time tt u var wbr img br".split())
DROPPED = frozenset("script style textarea title noscript iframe noembed noframes xmp head nav footer aside form template svg math canvas button select dialog menu object audio video map input fieldset datalist".split())
ROLES = frozenset("navigation banner contentinfo complementary search form dialog alertdialog alert menu menubar toolbar".split())
#: Words that tell what an element is for: fixed values.
UNWANTED = frozenset(
    "ad ads advert adverts advertisement advertising sponsor sponsored sponsors promo promotion banner nav navbar navigation menu menus breadcrumb breadcrumbs sidebar "
    "aside widget widgets related recommended recommendations share sharing social cookie cookies consent gdpr notice notices popup modal overlay newsletter subscribe "
    "subscription signup login signin comment comments disqus reply replies respond discussion footer pagination pager toolbar copyright masthead skip hidden".split()
)
#: Like these, but not inside an article, where they head it.
OUTSIDE = frozenset(("header", "topbar", "top", "head"))
#: Opening one of these ends an open paragraph; the others end a sibling of their own kind.
ENDS_P = frozenset("address article aside blockquote center details dialog dir div dl fieldset figcaption figure footer form h1 h2 h3 h4 h5 h6 header hgroup hr main menu nav ol p pre section table ul".split())
SIBLINGS = {"li": {"li"}, "dt": {"dt", "dd"}, "dd": {"dt", "dd"}, "tr": {"tr", "td", "th"}, "td": {"td", "th"}, "th": {"td", "th"}, "option": {"option"}, "thead": {"tr", "td", "th"}, "tbody": {"thead", "tr", "td", "th"}}
FENCES = {"li": {"ul", "ol", "menu"}, "dt": {"dl"}, "dd": {"dl"}, "tr": {"table"}, "td": {"table"}, "th": {"table"}, "thead": {"table"}, "tbody": {"table"}, "option": {"select"}}
#: Pages of different content that must agree before a constant node counts as template.
AGREE = 3
#: Nodes of a wrapper beyond which those that less than an eighth of their parent's pages have are left out.
WIDE = 4000


def attributes(text: str) -> dict[str, str]:
    return {k.lower(): (v[1:-1] if v[:1] in "\"'" else v) for k, v in ATTRIBUTE.findall(text)} if text.strip(" /") else {}


def unwanted(tag: str, attrs: dict[str, str], inside: bool) -> bool:
    """Whether an element is no main text by its name, role, class or id."""
    if tag in DROPPED or (tag == "header" and not inside):
        return True
    if not attrs or tag in ("html", "body", "main", "article"):
        return bool(attrs) and tag == "article" and not UNWANTED.isdisjoint(w.lower() for w in NAME.findall(attrs.get("class", "")))
    if attrs.get("role", "").lower() in ROLES or "hidden" in attrs or attrs.get("aria-hidden") == "true" or re.search(r"display\s*:\s*none", attrs.get("style", "")):
        return True
    words = {w.lower() for w in NAME.findall(attrs.get("class", "") + " " + attrs.get("id", ""))}
    return not words.isdisjoint(UNWANTED) or (not inside and not words.isdisjoint(OUTSIDE))


class Element:
    """A block element of a page: its name, with a sign where main text begins (main!), and the one it is in."""

    __slots__ = ("name", "parent")

    def __init__(self, name: str, parent: Element | None) -> None:
        self.name, self.parent = name, parent


class Block:
    """A stretch of text between block borders: the element it is in, text, and what is known about it."""

    __slots__ = ("at", "text", "kept", "region", "linked")

    def __init__(self, at: Element | None, text: str, kept: bool, region: int, linked: int) -> None:
        self.at, self.text, self.kept, self.region, self.linked = at, text, kept, region, linked


def blocks(page: str) -> list[Block]:
    """The text blocks of a page in order. Broken mark-up is read as browsers do, roughly: a paragraph ends
    where a block begins, an end tag without its start is passed over, and what is left open ends with the page.
    region: 2 inside an article, 1 inside a main element, else 0."""
    out: list[Block] = []
    stack: list[tuple[str, bool, int, Element | None]] = []  # tag, kept, region, innermost block element
    opened: Counter = Counter()  # tags on the stack
    kept, region, inner, links = True, 0, None, 0
    parts: list[str] = []
    linked = [0]

    def flush() -> None:
        if parts:
            text = " ".join(entities.unescape("".join(parts)).split())
            if text:
                out.append(Block(inner, text, kept, region, linked[0]))
            parts.clear()
        linked[0] = 0

    def pop(n: int) -> None:
        nonlocal kept, region, inner, links
        gone = stack[n:]
        if any(x[0] not in INLINE for x in gone) or kept != (stack[n - 1][1] if n else True):
            flush()
        for x in gone:
            links -= x[0] == "a"
            opened[x[0]] -= 1
        del stack[n:]
        kept, region, inner = stack[-1][1:] if stack else (True, 0, None)

    def last(tag: str) -> int:
        return next(i for i in range(len(stack) - 1, -1, -1) if stack[i][0] == tag)

    def text(piece: str) -> None:
        if piece:
            parts.append(piece)
            if links:
                linked[0] += len(piece)

    at, low = 0, None
    while m := TOKEN.search(page, at):
        text(page[at : m.start()])
        at, tag = m.end(), m[2]
        if not tag:
            continue
        tag = tag.lower()
        if m[1]:
            if opened[tag]:
                pop(last(tag))
            continue
        if tag in RAW:
            low = low if low is not None else page.lower()
            end = low.find("</" + tag, at) if len(low) == len(page) else page.find("</" + tag, at)
            close = page.find(">", end) if end >= 0 else -1
            at = close + 1 if close >= 0 else len(page)
            continue
        if tag in ENDS_P:
            if opened["p"] and not any(x[0] in ("td", "th", "table", "button", "object") for x in stack[last("p") :]):
                pop(last("p"))
        elif tag in SIBLINGS and any(opened[x] for x in SIBLINGS[tag]):
            for i in range(len(stack) - 1, -1, -1):
                if stack[i][0] in SIBLINGS[tag]:
                    pop(i)
                    break
                if stack[i][0] in FENCES.get(tag, ()):
                    break
        if tag in VOID:
            if tag == "br":
                parts.append(" ")
            elif tag == "hr":
                flush()
            continue
        attrs = attributes(m[3])
        here = kept and not unwanted(tag, attrs, region > 0)
        if tag not in INLINE or here != kept:
            flush()
        if m[3].endswith("/") and tag in ("svg", "path"):
            continue
        if here:
            region = 2 if tag == "article" else max(region, 1) if tag == "main" or attrs.get("role") == "main" else region
        if tag not in INLINE:
            main = here and (tag in ("article", "main") or attrs.get("role") == "main")
            inner = Element(tag + "." * bool(names := attrs.get("class", "").split()) + "".join(names[:1]) + "!" * main, inner)
        links += tag == "a"
        kept = here
        stack.append((tag, kept, region, inner))
        opened[tag] += 1
    text(page[at:])
    flush()
    return out


# Wrappers: a node is [name, pages, text, children]. Elements have the text "-"; a stretch of text is a leaf with
# its digest, or "" where it varies. An element that holds nothing but one stretch of text is a leaf itself.
# Nothing here recurses, so pages may be nested as deep as they like.
TEXT = "="


def mark(text: str) -> str:
    return blake2b(text.encode(), digest_size=8).hexdigest()


def tree(found: list[Block]) -> list:
    """The page's tree: every block element is a node of its own."""
    root: list = ["", 1, "-", []]
    nodes: dict[Element | None, list] = {None: root}
    for b in found:
        new, at = [], b.at
        while at not in nodes:
            new.append(at)
            at = at.parent
        node = nodes[at]
        for at in reversed(new):
            nodes[at] = child = [at.name, 1, "-", []]
            node[3].append(child)
            node = child
        node[3].append([TEXT, 1, mark(b.text), []])
    for node in nodes.values():
        if node is not root and len(node[3]) == 1 and node[3][0][0] == TEXT:
            node[2:] = node[3][0][2], []
    return root


def nodes_of(root: list) -> Iterator[tuple[int, list]]:
    """Depth and node of a tree, parents before their children and these in order."""
    waiting = [(0, root)]
    while waiting:
        depth, node = waiting.pop()
        yield depth, node
        waiting += [(depth + 1, c) for c in reversed(node[3])]


def flat(root: list) -> str:
    """A tree as text: depth, name, pages and text of every node."""
    return json.dumps([[depth, *node[:3]] for depth, node in nodes_of(root)], separators=(",", ":"))


def grown(text: str) -> list:
    """The tree that flat() wrote."""
    path: list[list] = []
    for depth, name, pages, leaf in json.loads(text):
        node = [name, pages, leaf, []]
        del path[depth:]
        if path:
            path[-1][3].append(node)
        path.append(node)
    return path[0]


def aligned(a: list, b: list, worth: dict) -> tuple[int, list[tuple[int, int]]]:
    """The match of two child lists that keeps order and is worth most, and its worth; worth has that of elements' children.

    Only equal names match, and elements with elements, leaves with leaves. Equal texts are worth more than a slot
    with whatever fills it, and that more than two single texts that make a slot. A text that most pages of its
    parent share is not given up for another one, so pages without it pass it by.
    """
    x, y = a[3], b[3]
    front, back = 0, 0  # equal leaves at both ends are always matched: nothing is worth more
    while front < min(len(x), len(y)) and x[front][2] not in ("", "-") and x[front][2] == y[front][2] and x[front][0] == y[front][0]:
        front += 1
    while back < min(len(x), len(y)) - front and x[-1 - back][2] not in ("", "-") and x[-1 - back][2] == y[-1 - back][2] and x[-1 - back][0] == y[-1 - back][0]:
        back += 1
    pairs = [(i, i) for i in range(front)]
    p, q = x[front : len(x) - back], y[front : len(y) - back]
    most = 8 * (front + back)
    if p and q:
        codes: dict[str, int] = {"": 0, "-": 1}
        code = lambda nodes, of: np.array([codes.setdefault(c[of], len(codes)) for c in nodes])
        free = lambda nodes, pages: np.array([c[2] != "-" and (c[2] == "" or c[1] == 1 or 2 * c[1] < pages) for c in nodes])
        same = code(p, 0)[:, None] == code(q, 0)[None, :]
        s, t = code(p, 2), code(q, 2)
        score = (free(p, a[1])[:, None] & free(q, b[1])[None, :]) * (1 + ((s == 0)[:, None] | (t == 0)[None, :]))
        score[(s[:, None] == t[None, :]) & (s > 1)[:, None]] = 8
        score *= same
        for i, j in zip(*np.nonzero(same & (s == 1)[:, None] & (t == 1)[None, :])):
            score[i, j] = 1 + worth[id(p[i]), id(q[j])][0]
        best = np.zeros((len(p) + 1, len(q) + 1), np.int64)
        for i in range(len(p)):
            np.maximum(best[i, 1:], best[i, :-1] + score[i], out=best[i + 1, 1:])
            np.maximum.accumulate(best[i + 1], out=best[i + 1])
        table, i, j, middle = best.tolist(), len(p), len(q), []
        while i and j:
            if table[i][j] == table[i - 1][j]:
                i -= 1
            elif table[i][j] == table[i][j - 1]:
                j -= 1
            else:
                i, j = i - 1, j - 1
                middle.append((front + i, front + j))
        most += table[-1][-1]
        pairs += middle[::-1]
    return most, pairs + [(len(x) - k, len(y) - k) for k in range(back, 0, -1)]


def matching(a: list, b: list) -> dict:
    """Simple tree matching of two trees: for every two elements that may match, the match of their children. Each pair
    of elements is looked at once, children before their parents."""
    worth: dict = {}
    waiting = [(a, b, False)]
    while waiting:
        p, q, ready = waiting.pop()
        if ready:
            worth[id(p), id(q)] = aligned(p, q, worth)
        elif (id(p), id(q)) not in worth:
            worth[id(p), id(q)] = (0, [])
            waiting.append((p, q, True))
            by: dict[str, list] = {}
            for c in q[3]:
                if c[2] == "-":
                    by.setdefault(c[0], []).append(c)
            waiting += [(c, d, False) for c in p[3] if c[2] == "-" for d in by.get(c[0], ())]
    return worth


def size_of_match(a: list, b: list) -> int:
    """Nodes that are matched."""
    if a[0] != b[0]:
        return 0
    worth, waiting, n = matching(a, b), [(a, b)], 0
    while waiting:
        p, q = waiting.pop()
        n += 1
        waiting += [(p[3][i], q[3][j]) for i, j in worth.get((id(p), id(q)), (0, []))[1]]
    return n


def merge(a: list, b: list) -> list:
    """The wrapper of the pages of both: aligned nodes add up and vary where their texts differ."""
    worth = matching(a, b)
    root = [a[0], a[1] + b[1], a[2] if a[2] == b[2] else "", []]
    waiting = [(a, b, root)]
    while waiting:
        p, q, out = waiting.pop()
        i = j = 0
        for k, l in [*worth[id(p), id(q)][1], (len(p[3]), len(q[3]))]:
            out[3] += p[3][i:k] + q[3][j:l]
            if k < len(p[3]):
                c, d = p[3][k], q[3][l]
                out[3].append([c[0], c[1] + d[1], c[2] if c[2] == d[2] else "", []])
                if c[2] == "-":
                    waiting.append((c, d, out[3][-1]))
            i, j = k + 1, l + 1
    return root


def wide(root: list, most: int = 0) -> bool:
    return sum(1 for _ in nodes_of(root)) > (most or WIDE)


def thinned(root: list, most: int = 0) -> list:
    """A wrapper of more than most nodes without those that few pages of their parent have. So pages of ever new shapes do
    not add up. What such rare nodes hold may yet be template: counted() has it for the hosts whose wrapper was thinned."""
    if wide(root, most):
        for _, node in nodes_of(root):
            node[3] = [c for c in node[3] if 8 * c[1] >= node[1]]
    return root


def template(root: list, least: int = AGREE) -> list[str]:
    """Names and text digests of a wrapper's constant leaves that enough pages share: at least half of those that have
    their parent, or the article or main element they are in. Their place may differ."""
    out, waiting = [], [(root, 0)]
    while waiting:
        node, main = waiting.pop()
        main = node[1] if not main and node[0].endswith("!") else main  # pages that have the element
        for c in node[3]:
            if c[2] not in ("", "-") and c[1] >= least and 2 * c[1] >= (main or node[1]):
                out.append(f"{node[0] if c[0] == TEXT else c[0]} {c[2]}")
        waiting += [(c, main) for c in node[3]]
    return out


def places(root: list) -> set[tuple[str, str]]:
    """(place, leaf) of a page's leaves as template() names them, and (place, "") of its elements. The place of a leaf is the
    path to the article or main element it is in, else to its parent."""
    out, waiting = set(), [(root, root[0], "")]
    while waiting:
        node, path, main = waiting.pop()
        main = path if not main and node[0].endswith("!") else main
        out.add((mark(path), ""))
        for c in node[3]:
            if c[2] == "-":
                waiting.append((c, f"{path} {c[0]}", main))
            elif c[2]:
                out.add((mark(main or path), f"{node[0] if c[0] == TEXT else c[0]} {c[2]}"))
    return out


def counted(trees: DataFrame, least: int = AGREE) -> DataFrame:
    """host, fixed: the leaves that at least half of a host's pages(host, tree) with their place share. Nothing is left out,
    however many shapes the pages have: counts are Spark's, and no task holds those of a host."""

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in batches:
            for host, text in zip(batch.column(0).to_pylist(), batch.column(1).to_pylist()):
                place, leaf = zip(*places(grown(text)))
                yield pa.RecordBatch.from_arrays([pa.array(c, pa.string()) for c in ([host] * len(place), place, leaf)], names=["host", "place", "leaf"])

    each = trees.select("host", "tree").mapInArrow(run, "host string, place string, leaf string").groupBy("host", "place", "leaf").agg(F.count(F.lit(1)).alias("k"))
    of = each.where("leaf = ''").select("host", "place", F.col("k").alias("pages"))
    shared = each.where(f"leaf <> '' AND k >= {least}").join(of, ["host", "place"]).where("2 * k >= pages")
    return shared.groupBy("host").agg(F.collect_set("leaf").alias("fixed"))


def main_text(page: str, constant: frozenset[str] | set[str] = frozenset()) -> list[str]:
    """The blocks of a page's main text that are not template. An article, else a main element, is taken where there
    is one; else all blocks that are neither unwanted nor mostly links."""
    return chosen(blocks(page), constant)


def chosen(found: list[Block], constant: frozenset[str] | set[str]) -> list[str]:
    fixed = lambda b: bool(constant) and f"{b.at.name if b.at else ''} {mark(b.text)}" in constant
    most = max((b.region for b in found if b.kept), default=0)
    rest = [b for b in found if b.kept and (b.region == most if most else 2 * b.linked <= len(b.text))]
    slots = [b.text for b in rest if not fixed(b)]
    return slots or [b.text for b in rest]  # pages that are all alike have no slots


def extracted(pages: DataFrame, separator: str = "\n\n") -> DataFrame:
    """page_id, url, text, n_chars of every page; a null html counts as empty and gives an empty text.

    Pages without a host share one wrapper. Repeated rows are extracted each, and count once for the wrapper. Very long and
    very deep pages are read whole. Other columns are not read. An empty table gives an empty result.
    """
    base = pages.select("page_id", "url", F.col("html").cast("string").alias("html"))
    base = base.withColumn("host", split(F.col("url"))[0])

    def read(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in batches:
            hosts, contents, trees = [], [], []
            for host, page in zip(batch.column(0).to_pylist(), batch.column(1).to_pylist()):
                found = blocks(page or "")
                hosts.append(host or "")
                contents.append(mark("\n".join(chosen(found, frozenset()))))
                trees.append(flat(tree(found)))
            yield pa.RecordBatch.from_arrays([pa.array(c, pa.string()) for c in (hosts, contents, trees)], names=["host", "content", "tree"])

    def fold(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        """Rows come host by host, so a task holds one wrapper."""
        at, wrapper, thin = None, None, False
        given = lambda: pa.RecordBatch.from_arrays([pa.array([at], pa.string()), pa.array([flat(wrapper)], pa.string()), pa.array([thin])], names=["host", "wrapper", "thin"])
        for batch in batches:
            for host, text in zip(batch.column(0).to_pylist(), batch.column(1).to_pylist()):
                if host != at and wrapper is not None:
                    yield given()
                    wrapper, thin = None, False
                at, wrapper = host, grown(text) if wrapper is None else merge(wrapper, grown(text))
                if wide(wrapper):
                    wrapper, thin = thinned(wrapper), True
        if wrapper is not None:
            yield given()

    def join(table: pa.Table) -> pa.Table:
        wrapper, thin = None, any(table.column("thin").to_pylist())
        for text in sorted(table.column("wrapper").to_pylist()):  # the same for every order of tasks
            wrapper = grown(text) if wrapper is None else merge(wrapper, grown(text))
            if wide(wrapper):
                wrapper, thin = thinned(wrapper), True
        return pa.table({"host": [table.column("host")[0].as_py()], "fixed": pa.array([template(wrapper)], pa.list_(pa.string())), "thin": [thin]})

    # Copies count once: of the pages of a host with the same main text, one goes into the wrapper.
    trees_of = lambda some: some.select("host", "html").mapInArrow(read, "host string, content string, tree string").groupBy("host", "content").agg(F.min("tree").alias("tree"))
    wrappers = trees_of(base).sortWithinPartitions("host", "content").select("host", "tree").mapInArrow(fold, "host string, wrapper string, thin boolean")
    fixed = materialize(wrappers.groupBy("host").applyInArrow(join, "host string, fixed array<string>, thin boolean"), "wrappers")
    thin = fixed.where("thin").select(F.col("host").alias("_host"))
    if thin.limit(1).count():  # what thinned wrappers left out is counted, for all pages of these hosts
        rest = counted(trees_of(base.join(thin, F.coalesce("host", F.lit("")) == F.col("_host"), "left_semi"))).withColumnRenamed("fixed", "more")
        fixed = fixed.join(rest, "host", "left").withColumn("fixed", F.array_union("fixed", F.coalesce("more", F.array().cast("array<string>"))))
        fixed = materialize(fixed.select("host", "fixed"), "wrappers")
    fixed = fixed.select("host", "fixed")

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in batches:
            texts, known = [], {}
            for host, page, constant in zip(batch.column("host").to_pylist(), batch.column("html").to_pylist(), batch.column("fixed")):
                if host not in known:
                    known[host] = frozenset(constant.as_py() or ())
                texts.append(separator.join(main_text(page or "", known[host])))
            yield pa.RecordBatch.from_arrays([batch.column("page_id"), batch.column("url"), pa.array(texts, pa.string()), pa.array(map(len, texts), pa.int64())], names=["page_id", "url", "text", "n_chars"])

    joined = base.join(fixed, "host", "left").select("host", "page_id", "url", "html", "fixed")
    return joined.mapInArrow(run, f"page_id {base.schema['page_id'].dataType.simpleString()}, url string, text string, n_chars bigint")
