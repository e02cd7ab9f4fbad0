"""HTML extraction by inferred wrappers: same-host pages are aligned into one union-free expression of groups and slots."""

from __future__ import annotations

import functools
import html as entities
import json
import re

import numpy as np
import pyarrow as pa
import xxhash
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from .common import map_arrow, settle

# ---- fixed values: what HTML's elements are, and words by which pages name parts that aren't the article ---------------
VOID = frozenset("area base br col embed hr img input link meta param source track wbr".split())
RAW = frozenset("script style noscript template iframe object svg textarea title head select button".split())
BLOCK = frozenset(
    "html body main article section header footer nav aside form div p h1 h2 h3 h4 h5 h6 ul ol li dl dt dd table thead tbody tfoot tr td th caption "
    "blockquote pre figure figcaption address details summary fieldset legend menu dialog center hr".split()
)
#: Elements that an opening tag of the key ends if they are open above the nearest element of the second set.
ENDS = {
    "li": ({"li", "p"}, {"ul", "ol", "menu"}), "dt": ({"dt", "dd", "p"}, {"dl"}), "dd": ({"dt", "dd", "p"}, {"dl"}), "tr": ({"tr", "td", "th", "p"}, {"table"}), "td": ({"td", "th", "p"}, {"tr", "table"}), "th": ({"td", "th", "p"}, {"tr", "table"}),
}
APART = frozenset("nav aside footer form dialog menu".split())
APART_ROLES = frozenset("navigation banner contentinfo complementary search dialog alert alertdialog form menu menubar".split())
#: Hints only: they decide on hosts of too few pages to align, and elsewhere where the wrapper has the element as optional or repeated.
APART_WORDS = frozenset(
    "ad ads advert advertisement adverts adsense sponsor sponsored promo promotion nav navbar navigation menu breadcrumb breadcrumbs pagination pager sidebar widget widgets "
    "related recommended cookie cookies consent gdpr notice notices notification alert popup modal overlay newsletter subscribe signup login search share sharing social "
    "comment comments disqus respond replies reply footer copyright skip hidden".split()
)
#: Only outside an article: inside one, these head the article itself.
HEAD_WORDS = frozenset("header masthead topbar banner".split())
# ------------------------------------------------------------------------------------------------------------------------

# Attribute parts stop at the next "<" outside quotes and are bounded, so that no stray "<" makes the rest of a page be read again and again.
_TOKEN = re.compile(r"<!--.*?(?:-->|\Z)|<[!?][^<>]*+>|<(/?)([a-zA-Z][a-zA-Z0-9:-]{0,99}+)((?:[^<>\"']{1,4000}+|\"[^\"]{0,4000}+\"|'[^']{0,4000}+'|[\"']){0,500}+)>", re.S)
_ATTR = re.compile(r"([^\s\"'>/=]+)(?:\s*=\s*(?:\"([^\"]*)\"|'([^']*)'|([^\s\"'>]+)))?")
_TELLING = frozenset("class id role hidden style itemprop aria-hidden".split())
_SPLIT = re.compile(r"[\s_:-]+|(?<=[a-z])(?=[A-Z])")
_HOST = re.compile(r"^[a-zA-Z][a-zA-Z0-9+.-]*://(?:[^/?#@]*@)?([^/?#:]*)")
PERIOD = 4
#: Trees of a host that one task aligns; levels of a tree (deeper elements count as their ancestor there); pairs of children aligned in order.
FAN_IN = 1000
DEPTH = 60
ALIGNED = 1 << 16


def host_of(url: str | None) -> str:
    m = _HOST.match(url or "")
    return m.group(1).lower() if m else ""


def _named(attrs: str) -> tuple[str, set[str], dict]:
    """The class or id that names an element in a path, all words of its class and id, and its other telling attributes."""
    if not attrs or attrs.isspace():
        return "", set(), {}
    found = {}
    for m in _ATTR.finditer(attrs):
        if (key := m.group(1).lower()) in _TELLING:
            found.setdefault(key, m.group(2) or m.group(3) or m.group(4) or "")
    names = f"{found.get('class', '')} {found.get('id', '')}".split()
    words = {w.lower() for n in names for w in _SPLIT.split(n) if w}
    # numbers in names (post-123) would make every page's path its own
    return re.sub(r"\d+", "0", "#".join(dict.fromkeys([names[0], names[-1]])))[:60] if names else "", words, found


class _Open:
    """An open element: its label path, node of the tree, and what holds for the blocks in it."""

    __slots__ = ("apart", "article", "depth", "first_apart", "label", "node", "path", "root", "tag", "worded")

    def __init__(self, tag, label, path, depth, node, apart=False, article=False, root=None, worded=-1, first_apart=0):
        self.tag, self.label, self.path, self.depth, self.node = tag, label, path, depth, node
        self.apart, self.article, self.root, self.worded, self.first_apart = apart, article, root, worded, first_apart


def parse(page: str) -> tuple[list[dict], list]:
    """Blocks of a page in order, and its tree [label, quantifier, children] with '#' for text.

    A block has its path, its text (references decoded, white space runs as one space), the characters inside links, the
    path of the outermost article or main part around it, whether it stands in a part that isn't an article by its tag,
    role or style (or in an article inside another one, as comments do), and whether words of a class or id hint at such
    a part. Text and tags inside raw elements are skipped. Missing end tags are met as browsers do for lists, tables and
    paragraphs; an article ends what was open around it of adverts and the like. Time is linear in the page; elements
    below DEPTH levels have the path of the element there.
    """
    tree = ["", "", []]
    stack = [_Open("", "", "", 0, tree[2])]
    counts: dict[str, int] = {}
    # of each element whose words hint: whether it stands in an article, and the one around it
    worded: list[tuple[bool, int]] = []
    blocks: list[dict] = []
    endless: set[str] = set()  # raw elements that no end tag follows any more
    text, linked, open_links, at = [], 0, 0, 0

    def flush():
        nonlocal linked
        joined = " ".join(entities.unescape("".join(text)).split())
        text.clear()
        if joined:
            top = stack[-1]
            blocks.append({"path": top.path, "text": joined, "linked": min(linked, len(joined)), "article": top.article, "apart": top.apart, "root": top.root, "worded": top.worded})
            top.node.append(["#", "", []])
        linked = 0

    def pop(depth: int):
        flush()
        for gone in stack[depth:]:
            counts[gone.tag] -= 1
        del stack[depth:]

    # nothing is a tag after the last ">", but a comment may begin there
    n, last = len(page), page.rfind(">") + 1
    last = n if page.find("<!--", last) >= 0 else last
    while at < n:
        m = _TOKEN.search(page, at, last) if at < last else None
        piece = page[at : m.start() if m else n]
        if piece:
            text.append(piece)
            if open_links:
                linked += len(piece.strip())
        if not m:
            break
        at = m.end()
        tag = (m.group(2) or "").lower()
        if not tag:
            continue
        closing, attrs = bool(m.group(1)), m.group(3)
        if tag == "br":
            text.append(" ")
        elif tag == "a":
            open_links = 0 if closing else 1
        elif tag in RAW:
            if not closing and not attrs.rstrip().endswith("/"):
                end = None if tag in endless else _raw_end(tag).search(page, at)
                if end:
                    at = end.end()
                else:
                    endless.add(tag)
                    at = n if tag in ("script", "style", "textarea", "title") else at
        elif tag in BLOCK and closing:
            open_links = 0
            if counts.get(tag):
                depth = len(stack) - 1
                while stack[depth].tag != tag:
                    depth -= 1
                pop(depth)
            else:
                flush()
        elif tag in BLOCK:
            flush()
            ends, within = ENDS.get(tag, (None, set()))
            ends = ends or {"p", *(("h1", "h2", "h3", "h4", "h5", "h6") if tag[0] == "h" and tag[1:].isdigit() else ())}
            while len(stack) > 1 and stack[-1].tag not in within and stack[-1].tag in ends:
                pop(len(stack) - 1)
            name, words, found = _named(attrs)
            role = found.get("role", "").lower()
            opens = tag in ("article", "main") or role in ("main", "article") or found.get("itemprop") == "articleBody"
            apart = (
                tag in APART
                or role in APART_ROLES
                or "hidden" in found
                or found.get("aria-hidden") == "true"
                or bool(re.search(r"display\s*:\s*none", found.get("style", "")))
                or (not stack[-1].article and tag == "header")
                or (tag == "article" and bool(counts.get("article")))
            )
            named = bool(words & APART_WORDS) or (not stack[-1].article and bool(words & HEAD_WORDS))
            # what an article with such words stands in may be the comments
            if opens and not apart and not named and not stack[-1].article and stack[-1].first_apart:
                pop(stack[-1].first_apart)
            if tag in VOID:
                continue
            top, label = stack[-1], f"{tag}.{name}" if name else tag
            if top.depth < DEPTH:
                node = [label, "", []]
                top.node.append(node)
                new = _Open(tag, label, f"{top.path}/{label}" if top.path else label, top.depth + 1, node[2])
            else:
                new = _Open(tag, top.label, top.path, top.depth, top.node)
            new.apart, new.article = top.apart or apart, top.article or (opens and not apart)
            new.root = top.root if top.article or not new.article else new.path
            new.worded = top.worded
            if named and (not (opens or tag in ("html", "body")) or counts.get("article")):
                new.worded = len(worded)
                worded.append((top.article, top.worded))
            new.first_apart = top.first_apart or (len(stack) if apart or new.worded != top.worded else 0)
            stack.append(new)
            counts[tag] = counts.get(tag, 0) + 1
    flush()
    _weigh(blocks, worded)
    return blocks, fold(tree)


@functools.cache
def _raw_end(tag: str) -> re.Pattern:
    return re.compile(rf"</{tag}\b[^<>]*+>", re.I)


def _weigh(blocks: list[dict], worded: list[tuple[bool, int]]) -> None:
    """Settles which blocks words hint to be apart: only where the element so named holds at most half of the unlinked text.

    Outside an article, an element that holds more is the content only if no article has text of its own.
    """
    held, total, articles = [0] * len(worded), 0, False
    for b in blocks:
        if not b["apart"]:
            own = len(b["text"]) - b["linked"]
            total += own
            articles |= b["article"] and b["worded"] < 0
            if b["worded"] >= 0:
                held[b["worded"]] += own
    for k in reversed(range(len(worded))):  # an element stands before those in it
        if worded[k][1] >= 0:
            held[worded[k][1]] += held[k]
    drop: list[bool] = []
    for k, (inside, around) in enumerate(worded):
        drop.append((around >= 0 and drop[around]) or held[k] * 2 <= total or (articles and not inside))
    for b in blocks:
        k = b.pop("worded")
        b["hinted"] = k >= 0 and drop[k]


def fold(node: list) -> list:
    """The tree with equal neighbours (or runs of up to PERIOD of them, again and again) as one repeated group."""
    return _fold(node)[0]


def _fold(node: list) -> tuple[list, int]:
    label, mark, children = node
    pairs = [_fold(c) for c in children]
    children, keys = [p[0] for p in pairs], [p[1] for p in pairs]
    for period in range(1, PERIOD + 1):
        out, out_keys, k = [], [], 0
        while k < len(children):
            times = 1
            while keys[k : k + period] == keys[k + times * period : k + (times + 1) * period] and len(keys[k : k + period]) == period:
                times += 1
            if times > 1:
                out += [[c[0], _repeat(c[1]), c[2]] for c in children[k : k + period]] if period == 1 else [["", "+", children[k : k + period]]]
                out_keys += keys[k : k + 1] if period == 1 else [_key_of("", keys[k : k + period])]
                k += times * period
            else:
                out.append(children[k])
                out_keys.append(keys[k])
                k += 1
        children, keys = out, out_keys
    return [label, mark, children], _key_of(label, keys)


def _key_of(label: str, keys: list[int]) -> int:
    """A number of a folded tree but for quantifiers."""
    return xxhash.xxh3_64_intdigest(f"{label} {keys}")


def _repeat(mark: str) -> str:
    return {"": "+", "?": "*"}.get(mark, mark)


def _maybe(mark: str) -> str:
    return {"": "?", "+": "*"}.get(mark, mark)


def align(a: list, b: list) -> list:
    """The least general tree of groups and slots that covers both: no alternatives, only optional and repeated parts.

    Children are aligned by label (longest common subsequence); what one side lacks becomes optional, what stands
    once on one side and repeatedly on the other repeated; equal neighbours that result are one repeated group.
    """
    mark = a[1] if a[1] == b[1] else _either(a[1], b[1])
    left, right = a[2], b[2]
    if not left or not right:
        return [a[0], mark, [[c[0], _maybe(c[1]), c[2]] for c in left or right]]
    if len(left) * len(right) > ALIGNED:
        return [a[0], mark, [["", "*", _alternatives(left + right)]]]
    size = np.zeros((len(left) + 1, len(right) + 1), np.int32)
    for i in range(len(left) - 1, -1, -1):
        for j in range(len(right) - 1, -1, -1):
            size[i, j] = size[i + 1, j + 1] + 1 if left[i][0] == right[j][0] else max(size[i + 1, j], size[i, j + 1])
    out, i, j = [], 0, 0
    while i < len(left) or j < len(right):
        if i < len(left) and j < len(right) and left[i][0] == right[j][0] and size[i, j] == size[i + 1, j + 1] + 1:
            out.append(align(left[i], right[j]))
            i, j = i + 1, j + 1
        elif j == len(right) or (i < len(left) and size[i + 1, j] >= size[i, j + 1]):
            out.append([left[i][0], _maybe(left[i][1]), left[i][2]])
            i += 1
        else:
            out.append([right[j][0], _maybe(right[j][1]), right[j][2]])
            j += 1
    merged: list = []
    for c in out:
        if merged and c[0] and merged[-1][0] == c[0]:
            both = align(merged[-1], c)
            needed = "" in (merged[-1][1], c[1]) or "+" in (merged[-1][1], c[1])
            merged[-1] = [c[0], "+" if needed else "*", both[2]]
        else:
            merged.append(c)
    return [a[0], mark, merged]


def _alternatives(children: list) -> list:
    """One optional part for each label among many children: repeated, they cover any order of them."""
    found: dict[str, list] = {}
    groups = []
    for c in children:
        if not c[0]:
            groups += _alternatives(c[2])
        else:
            found[c[0]] = align(found[c[0]], [c[0], "", c[2]]) if c[0] in found else [c[0], "", c[2]]
    for g in groups:
        found[g[0]] = align(found[g[0]], [g[0], "", g[2]]) if g[0] in found else g
    return [[label, "?", c[2]] for label, c in found.items()]


def _either(a: str, b: str) -> str:
    return ("*" if {"?", "*"} & {a, b} else "+") if {"+", "*"} & {a, b} else "?"


def expression(node: list) -> str:
    """A wrapper as text: tags, # for slots, and ? + * behind optional and repeated groups."""
    inner = " ".join(map(expression, node[2]))
    if node[0] == "#":
        return f"#{node[1]}"
    body = f"<{node[0]}>{' ' + inner if inner else ''} </{node[0].split('.')[0]}>" if node[0] else inner
    return f"({body}){node[1]}" if node[1] else body


def covers(wrapper: list, page: list) -> bool:
    """Whether a folded page is among those that the wrapper describes (unfolded groups count as their children)."""
    def fits(ws, ps):
        # reachable positions in ws after reading each child of the page
        at = {0}
        def skip(s):
            todo = list(s)
            while todo:
                k = todo.pop()
                if k < len(ws) and ws[k][1] in "?*" and ws[k][1] and k + 1 not in s:
                    s.add(k + 1)
                    todo.append(k + 1)
            return s
        at = skip(at)
        for p in ps:
            step = set()
            for k in at:
                if k < len(ws) and ws[k][0] == p[0] and fits(ws[k][2], p[2]) and (not p[1] or ws[k][1] in ("+", "*")):
                    step.add(k + 1)
                    if ws[k][1] in ("+", "*"):
                        step.add(k)
            at = skip(step)
        return len(ws) in at
    return fits(wrapper[2], page[2])


# ---- Spark -------------------------------------------------------------------------------------------------------------

_BLOCKS = "array<struct<path:string,text:string,linked:int,article:boolean,apart:boolean,root:string,hinted:boolean>>"


def parsed_pages(pages: DataFrame) -> DataFrame:
    """page_id, url, host, tree (JSON, folded) and blocks of every row; null html is the empty page."""
    kind = next(f.dataType for f in pages.schema if f.name == "page_id").simpleString()

    def run(batch):
        found = [parse(h or "") for h in batch.column("html").to_pylist()]
        urls = batch.column("url").to_pylist()
        return {"page_id": batch.column("page_id"), "url": urls, "host": [host_of(u) for u in urls], "tree": [json.dumps(t, separators=(",", ":")) for _, t in found], "blocks": [b for b, _ in found]}

    return map_arrow(pages.select("page_id", "url", "html"), run, f"page_id {kind}, url string, host string, tree string, blocks {_BLOCKS}")


def infer_wrappers(parsed: DataFrame, fan_in: int = FAN_IN) -> DataFrame:
    """host, n_pages, n_trees, wrapper (JSON): one expression for each host, from all its pages.

    Pages of one folded tree count once (a grouped sum), so a host's size is that of its variety. Trees are aligned one
    after another in parts of about fan_in, then the parts' wrappers likewise, until each host has one: no task holds
    more than a part, however many trees a host has.
    """

    def run(table: pa.Table) -> pa.Table:
        wrapper, pages, trees = None, 0, 0
        for r in table.sort_by([("n", "descending"), ("tree", "ascending")]).to_pylist():
            tree = json.loads(r["tree"])
            wrapper = tree if wrapper is None else align(wrapper, tree)
            pages, trees = pages + r["n"], trees + r["trees"]
        return pa.Table.from_pydict({"host": table.column("host").slice(0, 1), "tree": [json.dumps(wrapper, separators=(",", ":"))], "n": pa.array([pages], pa.int64()), "trees": pa.array([trees], pa.int64())})

    parts = parsed.groupBy("host", "tree").agg(F.count("*").alias("n")).withColumn("trees", F.lit(1).cast("long"))
    while True:
        parts = settle(parts, "html-trees")
        sizes = settle(parts.groupBy("host").agg(F.count("*").alias("in_host")), "html-sizes")
        if (sizes.agg(F.max("in_host")).first()[0] or 0) <= 1:
            return parts.select("host", F.col("n").alias("n_pages"), F.col("trees").alias("n_trees"), F.col("tree").alias("wrapper"))
        salt = F.pmod(F.xxhash64("tree"), F.ceil(F.col("in_host") / fan_in))
        parts = parts.join(sizes, "host").withColumn("salt", salt).drop("in_host").groupBy("host", "salt").applyInArrow(run, "host string, tree string, n bigint, trees bigint")


def slot_statistics(parsed: DataFrame) -> DataFrame:
    """host, path and what stands there over all pages of the host: pages, share of the pages' unlinked text, whether the text is always the same, hints, and the article around.

    Blocks in parts apart don't count. Every page weighs one, so that a page with a long thread of comments doesn't outweigh others.
    """
    plain = lambda b: F.length(b["text"]) - b["linked"]
    whole = F.aggregate(F.filter("blocks", lambda b: ~b["apart"]), F.lit(0), lambda s, b: s + plain(b))
    b = parsed.select("host", F.greatest(whole, F.lit(1)).alias("whole"), F.explode("blocks").alias("b")).where(~F.col("b.apart"))
    h = F.xxhash64("b.text")
    return b.groupBy("host", F.col("b.path").alias("path")).agg(
        F.count("*").alias("n"), F.sum((F.length("b.text") - F.col("b.linked")) / F.col("whole")).alias("share"), F.min(h).alias("lo"), F.max(h).alias("hi"), F.avg(F.col("b.hinted").cast("int")).alias("hinted"), F.max("b.root").alias("root")
    )


#: Pages of a host from which its wrapper decides; a text that stands at a place of so many without change is part of the template.
CONSTANT = 3


def slot_marks(node: list, above: str = "", loose: bool = False) -> dict[str, bool]:
    """Paths of the text slots of a wrapper, and whether each stands only in optional or repeated parts.

    Paragraphs, list items and the like are repeated in any text, so only elements around them count.
    """
    out: dict[str, bool] = {}
    for label, mark, children in node[2]:
        if label == "#":
            out[above] = out.get(above, True) and loose
            continue
        path = f"{above}/{label}" if above and label else label or above
        part = mark != "" and bool(label) and not _LEAF.fullmatch(label)
        for p, own in slot_marks([label, mark, children], path, loose or part or (not label and mark != "")).items():
            out[p] = out.get(p, True) and own
    return out


def content_paths(slots: DataFrame, wrappers: DataFrame) -> DataFrame:
    """host, the path of its content region, and the slots in it that are not content; a null region where too few pages were aligned.

    The wrapper tells data from template: a place whose text never changes, among no others that do, is template. A
    part that words hint to be no article goes if the wrapper has it as optional or repeated. The region is the deepest
    element with more than half of the remaining text of the pages, but no part of an article.
    """

    def run(table: pa.Table) -> pa.Table:
        rows = table.to_pylist()
        region, dropped = None, []
        if rows[0]["n_pages"] >= CONSTANT:
            marks = slot_marks(json.loads(rows[0]["wrapper"]))
            alive = {_container(r["path"]) for r in rows if not (r["n"] >= CONSTANT and r["lo"] == r["hi"])}
            dropped = [r["path"] for r in rows if _container(r["path"]) not in alive or (r["hinted"] * 2 > 1 and marks.get(r["path"], True))]
            gone, weight, roots = set(dropped), {}, {r["root"] for r in rows if r["root"]}
            for r in rows:
                if r["path"] not in gone:
                    at = -1
                    while at < len(r["path"]):
                        at = (r["path"].find("/", at + 1) + 1 or len(r["path"]) + 1) - 1
                        weight[r["path"][:at]] = weight.get(r["path"][:at], 0.0) + r["share"]
            region, total = "", sum(r["share"] for r in rows if r["path"] not in gone)
            inner = sorted((p for p, w in weight.items() if w * 2 > total and not any(p.startswith(f"{x}/") for x in roots)), key=lambda p: (p.count("/"), p))
            region = _container(inner[-1]) if inner else ""
        lists = pa.list_(pa.string())
        return pa.Table.from_arrays([table.column("host").slice(0, 1), pa.array([region], pa.string()), pa.array([sorted(dropped)], lists)], names=["host", "region", "dropped"])

    return slots.join(wrappers.select("host", "wrapper", "n_pages"), "host").groupBy("host").applyInArrow(run, "host string, region string, dropped array<string>")


_LEAF = re.compile(r"(p|h[1-6]|li|ul|ol|blockquote|pre|dd|dt|dl|figure|figcaption|td|tr|th|tbody|table)(\..*)?")


def _container(path: str) -> str:
    """The path without its last paragraph-like steps."""
    steps = path.split("/")
    while steps and _LEAF.fullmatch(steps[-1]):
        steps.pop()
    return "/".join(steps)


def extract(pages: DataFrame, broadcast_rows: int = 50_000) -> DataFrame:
    """page_id, url, text, n_chars of every row of pages.

    The aligned wrapper of a host and the text at its slots on all pages of the host say which region and which slots
    are content; on hosts of fewer than CONSTANT pages the page's own article, tags and hints do. Where an article
    holds most of the region's text on a page, it alone counts. Pages of all hosts, however hot, are parsed where they
    are read; only grouped counts and one row for each host are shuffled, and hosts beyond broadcast_rows are joined by
    a shuffle. A page with nothing in its host's region gives its article, or all its blocks that aren't apart, hinted
    at or mostly linked. Null or empty html gives an empty text; rows repeat as they stand; a null url is a host of its
    own; no rows give no rows.
    """
    parsed = settle(parsed_pages(pages), "html-parsed")
    wrappers = settle(infer_wrappers(parsed.select("host", "tree")), "html-wrappers")
    paths = settle(content_paths(slot_statistics(parsed.select("host", "blocks")), wrappers), "html-paths")
    few = paths.count() <= broadcast_rows
    both = parsed.join(F.broadcast(paths) if few else paths, "host", "left")
    plain = lambda b: F.length(b["text"]) - b["linked"]
    size = lambda blocks: F.aggregate(blocks, F.lit(0), lambda s, b: s + plain(b))
    inside = lambda b: (F.col("region") == "") | F.startswith(F.concat(b["path"], F.lit("/")), F.concat("region", F.lit("/")))
    both = both.withColumn("own", F.filter("blocks", lambda b: F.col("region").isNotNull() & ~b["apart"] & inside(b) & ~F.array_contains("dropped", b["path"])))
    both = both.withColumn("article", F.filter("own", lambda b: b["article"]))
    # the wrapper's region, less what is mostly linked where it is no article
    text_of = F.filter("own", lambda b: b["linked"] * 2 <= F.length(b["text"]))
    own = F.when(size(F.col("article")) * 2 > size(F.col("own")), F.col("article")).otherwise(text_of)
    alone = F.filter("blocks", lambda b: b["article"] & ~b["apart"] & ~b["hinted"])
    rest = F.filter("blocks", lambda b: ~b["apart"] & ~b["hinted"] & (b["linked"] * 2 <= F.length(b["text"])))
    chosen = F.when(F.size(own) > 0, own).when(F.size(alone) > 0, alone).otherwise(rest)
    text = F.coalesce(F.array_join(F.transform(chosen, lambda b: b["text"]), "\n"), F.lit(""))
    return both.select("page_id", "url", text.alias("text")).withColumn("n_chars", F.length("text").cast("long"))
