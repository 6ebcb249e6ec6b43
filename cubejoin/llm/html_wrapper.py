"""Main-text extraction by wrapper induction.

Pages of one host share a template.  Every page's DOM is aligned with the
host's exemplars (up to three pages of typical size in tags) by simple tree
matching, and counted for the first one that it fits.  A text that reads the
same at its place on nearly all different pages is template; what varies is a
slot.  Per host and exemplar, slots are weighed over all pages: characters that
vary and are not link text.  The content region is found by descending from the
root while one element holds nearly all of that weight, so menus, notices,
adverts and footers that vary from page to page fall outside, marked or not.

Tags, roles and class names are the prior of this decision: they scale a slot's
weight (down for navigation, footers, adverts and the like, up inside article or
main).  A region that meets an article or main element takes that element's
borders.  Inside the region, elements that are forms, navigation, comments or
adverts by their own tag or mark are left out; inside an article, text that is
the same on all pages stays.  Pages of a host with one page only, and pages that
fit no exemplar, have tags and marks alone.

Counting runs over all pages: each page emits its aligned slots, Spark counts
them per host with map-side combining.  No page set of a host meets in a task.
"""

from __future__ import annotations

import hashlib
import html
import re
from dataclasses import dataclass

import pyarrow as pa
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from .workspace import Workspace

VOID = frozenset("area base br col embed hr img input link meta param source track wbr".split())
RAW = frozenset("script style textarea title noscript template iframe xmp noembed noframes".split())
BLOCK = frozenset(
    "address article aside blockquote body caption center dd details dialog dir div dl dt fieldset figcaption figure footer form h1 h2 h3 h4 h5 h6 head header hgroup hr html legend li main menu nav ol p pre search section summary table tbody td tfoot th thead tr ul".split()
)
#: Elements that never hold article text.
DROPPED = frozenset("head script style textarea title noscript template iframe nav aside form button select input svg canvas object audio video dialog menu search".split())
ROLES = frozenset("navigation banner contentinfo complementary search alert alertdialog dialog form menu menubar toolbar status note".split())
#: Words of class and id values that mark what is no article text.
MARKS = frozenset(
    "ad ads adv advert adverts advertisement advertising banner sponsor sponsored promo promotion sidebar side nav navbar navigation menu breadcrumb breadcrumbs topbar header masthead footer cookie cookies consent gdpr notice notices notification alert popup modal overlay newsletter subscribe subscription signup login comment comments commentlist disqus respond reply replies discussion related recommended recommendations share sharing social widget toolbar pagination pager skip".split()
)
#: Marks that inside an article decide only as a whole class: elsewhere in a name they are layout or plain words.
SOFT = frozenset("header masthead footer side sidebar banner discussion related recommended notice notices alert reply replies respond navigation menu skip overlay social".split())
NEGATIONS = frozenset("no without has with hide".split())
#: Elements inside an article that no mark drops.
KEPT = frozenset("h1 h2 h3 h4 h5 h6 hgroup header section".split())
CLOSES_P = frozenset("address article aside blockquote details div dl fieldset figcaption figure footer form h1 h2 h3 h4 h5 h6 header hr main menu nav ol p pre section table ul".split())
#: An opening tag closes an open one of these, up to the given borders.
IMPLIED = {
    "li": (frozenset({"li"}), frozenset({"ul", "ol", "menu"})),
    "dt": (frozenset({"dt", "dd"}), frozenset({"dl"})),
    "dd": (frozenset({"dt", "dd"}), frozenset({"dl"})),
    "tr": (frozenset({"tr", "td", "th"}), frozenset({"table"})),
    "td": (frozenset({"td", "th"}), frozenset({"tr", "table"})),
    "th": (frozenset({"td", "th"}), frozenset({"tr", "table"})),
    "option": (frozenset({"option"}), frozenset({"select"})),
}
_TAG = re.compile(r"""<!--(?:>|->|.*?(?:--!?>|\Z))|<[!?][^>]*(?:>|\Z)|<(/?)([a-zA-Z][^\s/>]*)((?:[^>"']+|"[^"]*"|'[^']*'|["'])*?)(?:>|\Z)""", re.S)
_ATTRIBUTE = re.compile(r"""([^\s=/"'>]+)(?:\s*=\s*(?:"([^"]*)"|'([^']*)'|([^\s"'>]+)))?""")
_WORDS = re.compile(r"[A-Z]?[a-z]+|[A-Z]+")


@dataclass(frozen=True)
class WrapperSettings:
    """share: part of a host's different pages on which a template text is constant; pages: least
    number of different pages that can tell; hold: share of the weight that an element must have
    for the region to shrink to it, spare: characters a page that may be left outside at most;
    unlikely, likely: factors of slots under furniture and article elements; broadcast_bytes:
    largest total of exemplars, and of templates, that is broadcast."""

    share: float = 0.9
    pages: int = 2
    hold: float = 0.75
    spare: float = 250.0
    unlikely: float = 0.05
    likely: float = 3.0
    broadcast_bytes: int = 16 << 20


class Dom:
    """A page as parallel lists in document order; node 0 is the root."""

    __slots__ = ("tags", "parents", "children", "dropped", "own", "mains", "texts", "shapes", "sizes", "marks")

    def __init__(self, source: str):
        self.tags, self.parents, self.children = ["#root"], [-1], [[]]
        self.dropped, self.own, self.mains = [False], [False], [False]
        self.texts: list[tuple[int, str]] = []  # (node, raw text), in page order; (node, None) is a border
        self.marks: list[tuple[int, bool]] = []  # (node, whole class), for _settle
        self._parse(source)
        self._settle()
        self.shapes: list[int] = []
        self.sizes: list[int] = []

    def _add(self, tag: str, parent: int, attributes: str) -> int:
        node = len(self.tags)
        self.tags.append(tag)
        self.parents.append(parent)
        self.children.append([])
        self.children[parent].append(node)
        inside = self.mains[parent]
        own = tag in DROPPED or tag == "footer" or (tag == "header" and not inside)
        main = inside or tag == "article" or tag == "main"
        if attributes and not attributes.isspace():
            for m in _ATTRIBUTE.finditer(attributes):
                name = m[1].lower()
                value = m[2] if m[2] is not None else m[3] if m[3] is not None else m[4] or ""
                if name == "role":
                    role = value.strip().lower()
                    own = own or role in ROLES
                    main = main or role in ("main", "article")
                elif name == "hidden" or (name == "aria-hidden" and value == "true") or (name == "style" and "display:none" in value.replace(" ", "").lower()):
                    own = True
                elif name in ("class", "id") and tag not in ("html", "body", "article", "main"):
                    self._mark(node, tag, name, value, inside)
        self.own.append(own)
        self.dropped.append(own or self.dropped[parent])
        self.mains.append(main)
        return node

    def _mark(self, node: int, tag: str, name: str, value: str, inside: bool) -> None:
        """Notes whether a class or id value marks furniture; ``_settle`` decides."""
        if inside and tag in KEPT:
            return
        for token in value.split():
            words = [w.lower() for w in _WORDS.findall(token)]
            if len(words) == 1:
                if words[0] in MARKS and not (inside and (words[0] in ("header", "masthead") or (name == "id" and words[0] in SOFT))):
                    self.marks.append((node, True))
            elif not inside or name == "class":
                found = [w for i, w in enumerate(words) if w in MARKS and not (i and words[i - 1] in NEGATIONS)]
                if any(not inside or w not in SOFT for w in found):
                    self.marks.append((node, False))

    def _settle(self) -> None:
        """Marked elements drop with all they hold, save those that hold the article.

        That is the outermost article or main element with most text or, on a page
        without one, most of the text (for marks which are only part of a name).
        """
        if not self.marks:
            return
        n, parents, sizes = len(self.tags), self.parents, [0] * len(self.tags)
        tops = [x for x in range(1, n) if self.mains[x] and not self.mains[parents[x]] and not self.dropped[x]]
        out = self.dropped.copy()
        if not tops:
            for node, is_whole in self.marks:
                out[node] = out[node] or is_whole
            for node in range(1, n):
                out[node] = out[node] or out[parents[node]]
        for node, text in self.texts:
            if text and not out[node]:
                sizes[node] += len(text.strip())
        for node in range(n - 1, 0, -1):
            sizes[parents[node]] += sizes[node]
        holders = set()
        if tops:
            node = parents[max(tops, key=lambda x: (sizes[x], -x))]
            while node > 0:
                holders.add(node)
                node = parents[node]
        for node, is_whole in self.marks:
            holds = node in holders if tops else not is_whole and 2 * sizes[node] > sizes[0]
            self.own[node] = self.own[node] or not holds
            self.dropped[node] = self.dropped[node] or not holds
        for node in range(1, n):
            self.dropped[node] = self.dropped[node] or self.dropped[parents[node]]

    def _parse(self, source: str) -> None:
        at, open_node = 0, 0
        tags, parents, texts, search = self.tags, self.parents, self.texts, _TAG.search
        end = len(source)
        while at < end:
            m = search(source, at)
            if m is None:
                texts.append((open_node, source[at:]))
                break
            start, after = m.span()
            if start > at:
                texts.append((open_node, source[at:start]))
            at = after
            closing, name, attributes = m.group(1, 2, 3)
            if name is None:
                continue
            tag = name.lower()
            if closing:
                node = open_node
                while node > 0 and tags[node] != tag:
                    node = parents[node]
                if node > 0:
                    open_node = parents[node]
                if tag in BLOCK:
                    texts.append((open_node, None))
                elif tag == "br":
                    texts.append((open_node, " "))
                continue
            if tag in CLOSES_P:
                node = open_node
                while node > 0 and tags[node] != "p" and (tags[node] not in BLOCK):
                    node = parents[node]
                if tags[node] == "p":
                    open_node = parents[node]
            if tag in IMPLIED:
                closes, borders = IMPLIED[tag]
                node, found = open_node, -1
                while node > 0 and tags[node] not in borders:
                    if tags[node] in closes:
                        found = node
                    node = parents[node]
                if found > 0:
                    open_node = parents[found]
            node = self._add(tag, open_node, attributes)
            if tag in BLOCK:
                texts.append((node, None))
            if tag == "br":
                texts.append((node, " "))
            if tag in VOID or attributes.endswith("/") and tag not in BLOCK and tag not in RAW:
                continue
            if tag in RAW:
                close = re.compile(f"</{re.escape(tag)}(?=[\\s/>])[^>]*(?:>|\\Z)", re.I).search(source, at)
                at = close.end() if close else end
                continue
            open_node = node

    def shape(self) -> list[int]:
        """A number per node, equal for subtrees of equal structure."""
        if not self.shapes:
            shapes = [0] * len(self.tags)
            tags, children = self.tags, self.children
            for node in range(len(tags) - 1, -1, -1):
                shapes[node] = hash((tags[node], tuple([shapes[c] for c in children[node]])))
            self.shapes = shapes
        return self.shapes

    def subtree_sizes(self) -> list[int]:
        if not self.sizes:
            sizes = [1] * len(self.tags)
            for node in range(len(self.tags) - 1, 0, -1):
                sizes[self.parents[node]] += sizes[node]
            self.sizes = sizes
        return self.sizes

    def content_nodes(self) -> list[bool]:
        """Nodes that may hold article text by tags and marks alone: not dropped, inside article or main where there is one."""
        has_main = any(m and not d for m, d in zip(self.mains, self.dropped, strict=True))
        return [not d and (m or not has_main) for m, d in zip(self.mains, self.dropped, strict=True)]

    def region_nodes(self, root: int) -> tuple[list[bool], bool]:
        """Nodes that may hold article text if the content region is ``root``, and whether an article sets its borders."""
        parents, n = self.parents, len(self.tags)
        tops = [x for x in range(1, n) if self.mains[x] and not self.mains[parents[x]] and not self.dropped[x]]
        around, node = None, root
        while node > 0:
            if self.mains[node] and not self.mains[parents[node]]:
                around = node
            node = parents[node]
        inside = {root}
        if around is not None:
            inside = {around}
        else:
            below = [False] * n
            below[root] = True
            for x in range(root + 1, n):
                below[x] = below[parents[x]]
            held = {x for x in tops if below[x]}
            inside = held or inside
        allowed = [False] * n
        for x in range(n):
            allowed[x] = x in inside or (x > 0 and allowed[parents[x]] and not self.own[x])
        return allowed, around is not None or inside != {root}

    def blocks(self, allowed: list[bool]) -> list[tuple[int, str]]:
        """(first node, cleaned text) of each non-empty block of allowed nodes, in page order."""
        return [(node, text) for node, text, _ in self.linked_blocks(allowed)]

    def linked_blocks(self, allowed: list[bool] | None = None) -> list[tuple[int, str, float]]:
        """(first node, cleaned text, share of link text) of each non-empty block, in page order."""
        out: list[tuple[int, str, float]] = []
        parts: list[str] = []
        first, linked = -1, 0
        links: list[bool] = []
        for tag, parent in zip(self.tags, self.parents, strict=True):
            links.append(tag == "a" or (parent >= 0 and links[parent]))
        for node, text in [*self.texts, (0, None)]:
            if text is None:
                if parts:
                    raw = "".join(parts)
                    clean = " ".join(html.unescape(raw).split())
                    if clean:
                        out.append((first, clean, linked / len(raw)))
                    parts, first, linked = [], -1, 0
            elif allowed is None or allowed[node]:
                if first < 0 and not text.isspace():
                    first = node
                parts.append(text)
                linked += len(text) * links[node]
        return out


def tree_matching(page: Dom, model: Dom) -> dict[int, int]:
    """Simple tree matching: an order-keeping top-down alignment {page node: model node} of largest size.

    Equal roots match; their children align by dynamic programming over the
    sizes of their own alignments.  Structurally equal children at both ends are
    paired at once (no alignment can do better), so long runs of equal paragraphs
    cost linear time, and each pair of structures is solved once.  Nothing
    recurses, so depth is no matter.
    """
    a, b = page.shape(), model.shape()
    sizes = page.subtree_sizes()
    # (shape, shape) -> size and aligned children as index pairs
    solved: dict[tuple[int, int], tuple[int, list[tuple[int, int]]]] = {}
    todo = [(0, 0)]
    while todo:
        x, y = todo[-1]
        key = (a[x], b[y])
        if key in solved:
            todo.pop()
            continue
        if page.tags[x] != model.tags[y]:
            solved[key] = (0, [])
            continue
        if key[0] == key[1]:
            solved[key] = (sizes[x], [(i, i) for i in range(len(page.children[x]))])
            continue
        left, right = page.children[x], model.children[y]
        lo = 0
        while lo < len(left) and lo < len(right) and a[left[lo]] == b[right[lo]]:
            lo += 1
        cut = 0
        while cut < min(len(left), len(right)) - lo and a[left[-1 - cut]] == b[right[-1 - cut]]:
            cut += 1
        middle_l, middle_r = left[lo : len(left) - cut], right[lo : len(right) - cut]
        firsts = {(a[u], b[v]): (u, v) for u in {a[u]: u for u in middle_l}.values() for v in {b[v]: v for v in middle_r}.values()}
        missing = [pair for shapes, pair in firsts.items() if shapes not in solved]
        if missing:
            todo += missing
            continue
        pairs = [(i, i) for i in range(lo)] + [(len(left) - 1 - i, len(right) - 1 - i) for i in range(cut)]
        size = 1 + sum(sizes[left[i]] for i, _ in pairs)
        if middle_l and middle_r:
            width = len(middle_r) + 1
            best = [0] * width
            rows = [best]
            for u in middle_l:
                row = [0] * width
                gains = [solved[a[u], b[v]][0] for v in middle_r]
                for j, gain in enumerate(gains):
                    row[j + 1] = max(row[j], best[j + 1], best[j] + gain)
                rows.append(row)
                best = row
            size += best[-1]
            i, j = len(middle_l), len(middle_r)
            while i and j:
                if rows[i][j] == rows[i - 1][j]:
                    i -= 1
                elif rows[i][j] == rows[i][j - 1]:
                    j -= 1
                else:
                    i, j = i - 1, j - 1
                    pairs.append((lo + i, lo + j))
        solved[key] = (size, pairs)
    found: dict[int, int] = {}
    open_pairs = [(0, 0)] if page.tags[0] == model.tags[0] else []
    while open_pairs:
        x, y = open_pairs.pop()
        found[x] = y
        left, right = page.children[x], model.children[y]
        if a[x] == b[y]:  # equal structures align child by child
            open_pairs += zip(left, right, strict=True)
        else:
            open_pairs += [(left[i], right[j]) for i, j in solved[a[x], b[y]][1]]
    return found


def _digest(text: str) -> int:
    return int.from_bytes(hashlib.blake2b(text.encode("utf-8", "surrogatepass"), digest_size=8).digest(), "little", signed=True)


class _Exemplars:
    """Parsed exemplars and their regions: rows arrive host by host or repeat few hosts."""

    def __init__(self):
        self.kept: dict[str, Dom] = {}
        self.regions: dict[tuple, int] = {}

    def dom(self, source: str) -> Dom:
        if source not in self.kept:
            if len(self.kept) >= 64:
                self.kept.clear()
                self.regions.clear()
            self.kept[source] = Dom(source)
        return self.kept[source]

    def region(self, source: str, slots: list[tuple[int, int, float]], settings: WrapperSettings) -> int:
        key = (source, tuple(slots), settings)
        if key not in self.regions:
            self.regions[key] = content_region(self.dom(source), slots, settings)
        return self.regions[key]


def fitting_exemplar(page: Dom, models: list[Dom], allowed: set[int] | None = None) -> tuple[int, dict[int, int]] | None:
    """The first exemplar half of whose nodes align with the page's, and the alignment."""
    for k, model in enumerate(models):
        if allowed is None or k in allowed:
            matching = tree_matching(page, model)
            if 2 * len(matching) >= max(len(model.tags), len(page.tags) / 4):
                return k, matching
    return None


def _slot(page: Dom, matching: dict[int, int], node: int) -> int:
    """Exemplar node of the nearest aligned element around a text."""
    while node not in matching:
        node = page.parents[node]
    return matching[node]


def content_region(model: Dom, slots: list[tuple[int, int, float]], settings: WrapperSettings) -> int:
    """The exemplar element that holds the host's content: slots are (node, pages, varying characters that are no link)."""
    weight = [0.0] * len(model.tags)
    plain = [0.0] * len(model.tags)
    pages = max((n for _, n, _ in slots), default=1)
    for node, _, chars in slots:
        plain[node] += chars / pages
        weight[node] += chars / pages * (settings.unlikely if model.dropped[node] else settings.likely if model.mains[node] else 1.0)
    for node in range(len(model.tags) - 1, 0, -1):
        weight[model.parents[node]] += weight[node]
    # What is likely furniture may be left outside whatever its length.
    likely = [0.0 if model.dropped[n] else x for n, x in enumerate(plain)]
    for node in range(len(model.tags) - 1, 0, -1):
        likely[model.parents[node]] += likely[node]
    node = 0
    while weight[node] > 0:
        heavy = max(model.children[node], key=lambda c: (weight[c], -c), default=-1)
        if heavy < 0 or not any(model.tags[c] in BLOCK for c in model.children[heavy]):
            break  # a block of text is no region: others may stand beside it on other pages
        if weight[heavy] < settings.hold * weight[node] or likely[node] - likely[heavy] > max(settings.spare, 0.0) and not model.mains[heavy]:
            break
        node = heavy
    return node


def _count_kernel(batches):
    exemplars = _Exemplars()
    for batch in batches:
        for lo in range(0, batch.num_rows, 256):
            part = batch.slice(lo, 256)
            hosts, digests, fitting, nodes = [], [], [], []
            for host, source, models in zip(*(part.column(i).to_pylist() for i in range(3)), strict=True):
                page = Dom(source)
                found = fitting_exemplar(page, [exemplars.dom(m) for m in models])
                if found is None:
                    continue
                k, matching = found
                blocks = page.linked_blocks()
                hosts.append(host)
                digests.append(_digest("\n".join(t for _, t, _ in blocks)))
                fitting.append(k)
                nodes.append([{"node": _slot(page, matching, n), "text": _digest(t), "chars": round(len(t) * (1 - linked))} for n, t, linked in blocks])
            kind = pa.list_(pa.struct([("node", pa.int32()), ("text", pa.int64()), ("chars", pa.int64())]))
            yield pa.RecordBatch.from_arrays([pa.array(hosts, pa.string()), pa.array(digests, pa.int64()), pa.array(fitting, pa.int32()), pa.array(nodes, kind)], names=["host", "page", "exemplar", "nodes"])


def page_text(page: Dom, models: list[str], template: list[dict], exemplars: _Exemplars, settings: WrapperSettings) -> str:
    """The article of a page of a host with a template: rows (exemplar, constant texts, slots)."""
    known = {t["exemplar"]: t for t in template}
    found = fitting_exemplar(page, [exemplars.dom(m) for m in models], set(known))
    if found is None:
        return "\n".join(t for _, t in page.blocks(page.content_nodes()))
    k, matching = found
    constant = {(c["node"], c["text"]) for c in known[k]["constants"]}
    model = exemplars.dom(models[k])
    at = exemplars.region(models[k], [(s["node"], s["pages"], s["chars"]) for s in sorted(known[k]["slots"], key=lambda s: s["node"])], settings)
    placed = {y: x for x, y in matching.items()}
    while at not in placed:
        at = model.parents[at]
    root = placed[at]
    allowed, by_article = page.region_nodes(root)
    if by_article:
        return "\n".join(t for _, t in page.blocks(allowed))
    # A heading above the region belongs to it.
    for x in range(1, root):
        if page.tags[x] in ("h1", "h2") and not page.dropped[x]:
            allowed[x] = True
        elif x not in _path(page, root) and allowed[page.parents[x]] and page.parents[x] not in _path(page, root):
            allowed[x] = not page.own[x]
    return "\n".join(t for n, t in page.blocks(allowed) if (_slot(page, matching, n), _digest(t)) not in constant)


def _path(page: Dom, node: int) -> set[int]:
    out = set()
    while node >= 0:
        out.add(node)
        node = page.parents[node]
    return out


def _extract_kernel(settings: WrapperSettings):
    def run(batches):
        exemplars = _Exemplars()
        for batch in batches:
            for lo in range(0, batch.num_rows, 256):
                part = batch.slice(lo, 256)
                texts = []
                for source, models, template in zip(*(part.column(i).to_pylist() for i in range(2, 5)), strict=True):
                    page = Dom(source or "")
                    texts.append(page_text(page, models, template, exemplars, settings) if template and source else "\n".join(t for _, t in page.blocks(page.content_nodes())))
                yield pa.RecordBatch.from_arrays(
                    [part.column(0), part.column(1), pa.array(texts, pa.string()), pa.array(list(map(len, texts)), pa.int64())],
                    names=["page_id", "url", "text", "n_chars"],
                )

    return run


def extract(spark: SparkSession, pages: DataFrame, settings: WrapperSettings = WrapperSettings()) -> DataFrame:
    """page_id, url, text, n_chars of every page.

    Null html counts as empty (text ""); a null or odd url has the host "" and
    is treated alone with its like; hosts with fewer than ``pages`` different
    pages (that is one, by default) have no template; repeated rows give repeated rows; an empty table
    gives none; extra columns are ignored.
    """
    work = Workspace(spark, "wrapper")
    host = F.coalesce(F.regexp_extract(F.lower("url"), r"^[a-z][a-z0-9+.-]*://([^/?#]*)", 1), F.lit(""))
    rows = pages.select(F.col("page_id").cast("long").alias("page_id"), F.col("url").cast("string").alias("url"), F.col("html").cast("string").alias("html")).withColumn("host", host)
    filled = rows.where("html is not null and html <> ''")
    # Typical pages: those nearest to the quartiles of the host's page sizes in tags.
    sized = filled.withColumn("tags", F.length("html") - F.length(F.replace("html", F.lit("<"), F.lit(""))))
    typical = sized.groupBy("host").agg(F.percentile_approx("tags", [0.5, 0.25, 0.75]).alias("q"), F.count("*").alias("c")).where(F.col("c") >= settings.pages)
    typical = work.table("typical", typical.select("host", "q"))
    near = lambda k: F.min(F.struct(F.abs(F.col("tags") - F.col("q")[k]).alias("d"), F.col("page_id").alias("id"), F.length("html").alias("n")))
    picked = sized.select("host", "page_id", "tags", "html").join(F.broadcast(typical) if typical.count() <= 100_000 else typical, "host").groupBy("host").agg(*[near(k).alias(f"m{k}") for k in range(3)])
    picked = picked.select("host", F.posexplode(F.array_distinct(F.array("m0.id", "m1.id", "m2.id"))).alias("turn", "page_id"), (F.col("m0.n") + F.col("m1.n") + F.col("m2.n")).alias("n"))
    picked = work.table("picked", picked)
    total = picked.agg(F.sum("n").alias("n")).first().n or 0
    small = total * 4 <= settings.broadcast_bytes  # bytes of all exemplars at most
    chosen = F.broadcast(picked.drop("n")) if small else picked.drop("n")
    exemplars = filled.join(chosen, ["host", "page_id"]).groupBy("host", "page_id").agg(F.min("turn").alias("turn"), F.min("html").alias("html"))
    exemplars = exemplars.groupBy("host").agg(F.transform(F.array_sort(F.collect_list(F.struct("turn", "html"))), lambda x: x["html"]).alias("exemplar"))  # three at most
    exemplars = work.table("exemplars", exemplars)
    known = F.broadcast(exemplars) if small else exemplars

    seen = filled.join(known, "host").select("host", "html", "exemplar")
    # Equal pages count once; a page's slots follow from its digest, so any copy will do.
    counted = work.table("counted", seen.mapInArrow(_count_kernel, "host string, page long, exemplar int, nodes array<struct<node:int,text:long,chars:long>>"))
    at = ["host", "exemplar"]
    n_pages = counted.groupBy(*at).agg(F.countDistinct("page").alias("pages")).where(F.col("pages") >= settings.pages)
    n_pages = work.table("n_pages", n_pages)
    n_pages = F.broadcast(n_pages) if n_pages.count() <= 100_000 else n_pages
    nodes = counted.select(*at, "page", F.explode("nodes").alias("x")).select(*at, "page", "x.node", "x.text", "x.chars").distinct()
    texts = nodes.groupBy(*at, "node", "text").agg(F.count("*").alias("c"), F.sum("chars").alias("chars")).join(n_pages, at)
    fixed = F.col("c") >= settings.share * F.col("pages")
    slots = texts.groupBy(*at, "node").agg(
        F.max("pages").alias("pages"),
        F.coalesce(F.sum(F.when(~fixed, F.col("chars"))), F.lit(0)).alias("chars"),
        F.collect_set(F.when(fixed, F.col("text"))).alias("texts"),  # a page's texts at most: each is on nearly all pages
    )
    slots = slots.groupBy(*at).agg(
        F.flatten(F.collect_list(F.transform("texts", lambda t: F.struct(F.col("node").alias("node"), t.alias("text"))))).alias("constants"),
        F.collect_list(F.struct("node", "pages", "chars")).alias("slots"),
    )
    templates = slots.groupBy("host").agg(F.collect_list(F.struct("exemplar", "constants", "slots")).alias("template"))  # three at most
    templates = work.table("templates", exemplars.join(templates, "host"))

    weight = templates.agg(F.sum(F.aggregate("exemplar", F.lit(0).cast("long"), lambda n, e: n + F.octet_length(e)) + F.aggregate("template", F.lit(0).cast("long"), lambda n, t: n + 64 * (F.size(t["slots"]) + F.size(t["constants"])))).alias("n")).first().n or 0
    known = F.broadcast(templates) if weight <= settings.broadcast_bytes else templates
    joined = rows.join(known, "host", "left").select("page_id", "url", "html", "exemplar", "template")
    work.keep("templates")
    return joined.mapInArrow(_extract_kernel(settings), "page_id long, url string, text string, n_chars long")
