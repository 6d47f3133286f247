"""Main text of web pages by consensus host paths.

A tolerant parser gives each page's text blocks in a tree of their containers, in one pass. Every page scores its containers, from the leaves up: the text that they hold outside links and
hidden or navigational elements. Words in classes and ids that often name boilerplate are a score, not a verdict: such an element's text does not count for the containers around it, and
it counts less for the element itself. Pages vote for the path of their best container, generalised to tags and classes without numbers, with its score; Spark sums the votes of a host.
Each page is then read again through its host's winning path, and where that path does not hold most of the page's own best container, through the latter."""

from __future__ import annotations

import re
from collections import defaultdict
from collections.abc import Iterator
from html import unescape
from itertools import groupby

import pyarrow as pa
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from entitygraph.shared import materialise

#: Elements without an end tag, those whose content is no markup, those that are never main text, and those that end a block (fixed values of HTML).
VOID = frozenset("area base br col embed hr img input link meta param source track wbr".split())
RAW = frozenset("script style noscript template textarea title iframe xmp noframes".split())
NEVER = frozenset("nav footer aside button select option datalist menu dialog svg canvas audio video object map head".split()) | RAW
INLINE = frozenset("a abbr acronym b bdi bdo big cite code data del dfn em font i ins kbd label mark q rp rt ruby s samp small span strike strong sub sup time tt u var wbr".split())
CONTAINERS = frozenset("article main section div td body content center".split())
#: An open element of the second kind ends when one of the first opens (fixed values of HTML).
CLOSED_BY = {
    "p": frozenset("p div ul ol dl table article section main header footer aside nav form h1 h2 h3 h4 h5 h6 hr pre blockquote address figure fieldset details".split()),
    "li": frozenset(["li"]), "dt": frozenset(["dt", "dd"]), "dd": frozenset(["dt", "dd"]), "option": frozenset(["option"]),
    "tr": frozenset(["tr", "tbody", "tfoot"]), "td": frozenset(["td", "th", "tr"]), "th": frozenset(["td", "th", "tr"]),
}
#: Elements that lower the score of what they hold, as the words below do.
SOFT = frozenset(["form"])
#: Words in a class, id or role that often mark boilerplate.
NOISE = frozenset(
    "ad ads adv advert adverts advertisement advertising banner breadcrumb breadcrumbs comment comments commentlist consent cookie cookies disqus footer header masthead menu "
    "modal nav navbar navigation newsletter notice notices notification pagination pager popup promo promoted promotion related recommended reply replies respond share sharing "
    "sidebar signup social sponsor sponsored subscribe subscription toolbar widget widgets complementary contentinfo search feedback gdpr discussion".split()
)
HOST_ROWS = 200_000
#: Share of a page's own best container that its host's path must hold to be taken.
MOST = 0.8
#: What is left of a container's score for each marked element that it lies in or is.
MARKED = 0.3
#: Possessive throughout: a tag whose quotes don't close ends at its first bracket, and nothing is tried twice.
_token = re.compile(
    r"<!--.*?(?:-->|\Z)|<!\[CDATA\[.*?(?:\]\]>|\Z)|<[!?][^>]*+>|<(/?)([a-zA-Z][^\s/>]*+)((?>[^>\"']*+(?:(?:\"[^\"]*+\"|'[^']*+')[^>\"']*+)*+(?=>|\Z)|[^>]*+))(?:>|\Z)", re.S
)
_attributes = re.compile(r"([^\s\"'>/=]+)(?:\s*=\s*(?:\"([^\"]*)\"|'([^']*)'|([^\s\"'>]+)))?")
_unseen = re.compile(r"(?:^|;)\s*(?:display\s*:\s*none|visibility\s*:\s*(?:hidden|collapse))\s*(?:!\s*important\s*)?(?=;|$)", re.I)
#: Classes of the common style sheets that take an element off the page.
UNSEEN = frozenset("hidden d-none is-hidden visually-hidden sr-only".split())
_raw_end = {t: re.compile(rf"</{t}\s*>", re.I) for t in RAW}
_number = re.compile(r"[-_]*[0-9]+$")


def host_of(url: str | None) -> str:
    found = re.match(r"(?:[a-z][a-z0-9+.-]*:)?//(?:[^/?#@]*@)?([^/?#:]*)", url or "", re.I)
    return found[1].lower() if found else ""


def _label(tag: str, attributes: str) -> tuple[str, bool, bool]:
    """The element's place in a generalised path, whether its marks name boilerplate, and whether it is off the page."""
    if not attributes:
        return tag, False, False
    name, marked, unseen = tag, False, False
    for kind, *values in _attributes.findall(attributes):
        kind, value = kind.lower(), unescape("".join(values)).lower()
        if kind in ("class", "id", "role"):
            marks = value.split()
            marked |= any(_number.sub("", m) in NOISE for m in marks)
            if kind == "class":
                unseen |= any(m in UNSEEN for m in marks)
                name = f"{tag}.{'.'.join(sorted(set(re.sub(r'[0-9]+', '', value).split())))}"
        elif kind == "hidden":  # a boolean: any value hides
            unseen = True
        elif kind == "aria-hidden":
            unseen |= value.strip() == "true"
        elif kind == "style":
            unseen |= bool(_unseen.search(value))
    return name, marked, unseen


class Page:
    """The containers of a page as a tree, where equal paths are one node, and its text blocks in order.

    Node 0 is the page itself. ``bar`` of a node or block is the least depth from which on containers may count it: that of the innermost marked element around it."""

    def __init__(self):
        self.parent, self.place, self.depth, self.marks, self.bar = [0], [""], [0], [0], [0]
        self.known: dict[tuple[int, str, int, int], int] = {}
        self.blocks: list[tuple[int, int, str, int]] = []  # node, bar, text, characters in links

    def node(self, parent: int, place: str, bar: int, marks: int) -> int:
        found = self.known.setdefault((parent, place, bar, marks), len(self.parent))
        if found == len(self.parent):
            self.parent.append(parent)
            self.place.append(place)
            self.depth.append(self.depth[parent] + 1)
            self.marks.append(marks)
            self.bar.append(bar)
        return found

    def path(self, node: int) -> list[str]:
        out = []
        while node:
            out.append(self.place[node])
            node = self.parent[node]
        return out[::-1]


class _Open:
    __slots__ = ("tag", "node", "bar", "marks", "hides", "sets_apart", "live")

    def __init__(self, tag: str, node: int, bar: int, marks: int, hides: bool, sets_apart: bool):
        self.tag, self.node, self.bar, self.marks, self.hides, self.sets_apart, self.live = tag, node, bar, marks, hides, sets_apart, True


def page_of(html: str) -> Page:
    """One pass over the page; each element is opened and closed once, whatever the nesting. Hidden and navigational text is left out."""
    page = Page()
    root = _Open("", 0, 0, 0, False, False)
    stack: list[_Open] = []
    places: dict[str, list[int]] = defaultdict(list)  # of each tag, where on the stack it is open
    walls: list[int] = []  # where on the stack elements other than inline ones are
    held: list[str] = []
    hidden = linked = at = 0
    n = len(html)

    def flush() -> None:
        nonlocal linked
        if not held:
            return
        text = " ".join("".join(held).split())
        if text and not hidden:
            top = stack[-1] if stack else root
            page.blocks.append((top.node, top.bar, text, min(linked, len(text))))
        held.clear()
        linked = 0

    def say(text: str) -> None:
        nonlocal linked
        if text:
            if "&" in text:
                text = unescape(text)
            held.append(text)
            if places["a"]:
                linked += len(text.strip())

    def close(x: _Open) -> None:
        nonlocal hidden
        places[x.tag].pop()
        hidden -= x.hides
        x.live = False

    def pop() -> _Open:
        x = stack.pop()
        if walls and walls[-1] == len(stack):
            walls.pop()
        if x.live:
            close(x)
        while stack and not stack[-1].live:
            stack.pop()
        return x

    while at < n:
        found = _token.search(html, at)
        if not found:
            say(html[at:])
            break
        say(html[at : found.start()])
        at = found.end()
        if found[0].startswith("<![CDATA["):
            say(found[0][9:].removesuffix("]]>"))
            continue
        if not found[2]:
            continue
        tag = found[2].lower()
        if found[1]:
            if tag in INLINE:
                if places[tag] and (not walls or places[tag][-1] > walls[-1]):
                    k = places[tag][-1]
                    if stack[k].sets_apart:
                        flush()
                    close(stack[k])
                    while stack and not stack[-1].live:
                        stack.pop()
            else:
                flush()
                if places[tag]:
                    while pop().tag != tag:
                        pass
            continue
        if tag not in INLINE:
            flush()
            while stack and stack[-1].tag in INLINE and tag in CLOSED_BY["p"]:
                pop()
            while stack and tag in CLOSED_BY.get(stack[-1].tag, ()):
                pop()
        if tag in VOID or (found[3] or "").endswith("/") and tag not in CONTAINERS:
            continue
        if tag in RAW:
            end = _raw_end[tag].search(html, at)
            at = end.end() if end else n
            continue
        place, marked, unseen = _label(tag, found[3] or "")
        marked = (marked or tag in SOFT) and tag not in ("body", "html", "article", "main")
        hides = (unseen and tag not in ("body", "html")) or tag in NEVER or (tag == "header" and not places["article"] and not places["main"])
        if tag in INLINE and (hides or marked):
            flush()
        above = stack[-1] if stack else root
        marks, bar = above.marks + marked, above.bar
        if marked:
            bar = page.depth[above.node] + 1  # a marked element that is no container lies below every container around it
        node = page.node(above.node, place, bar, marks) if tag in CONTAINERS else above.node
        if tag not in INLINE:
            walls.append(len(stack))
        places[tag].append(len(stack))
        stack.append(_Open(tag, node, bar, marks, hides, hides or marked))
        hidden += hides
    flush()
    return page


def best_container(page: Page) -> tuple[int, float] | None:
    """The deepest container that scores at least four fifths of the best, one that is named an article or main half, and its score.
    While text that is not mostly links lies beside it in its parent, the parent takes its place."""
    size = len(page.parent)
    held, count = [0.0] * size, [0] * size
    for node, bar, text, linked in page.blocks:
        if page.depth[node] >= bar:
            held[node] += len(text) - 2 * linked
            count[node] += len(text) > 2 * linked
    for node in range(size - 1, 0, -1):  # children come after their parents
        up = page.parent[node]
        if page.bar[node] <= page.depth[up]:
            held[up] += held[node]
            count[up] += count[node]
    named = [p.split(".")[0] in ("article", "main") for p in page.place]
    score = [h * MARKED**m for h, m in zip(held, page.marks, strict=True)]
    top = max(score[1:], default=0)
    if top <= 0:
        return None
    enough = [i for i in range(1, size) if score[i] > 0 and score[i] >= (0.5 if named[i] else 0.8) * top]
    best = max(enough, key=lambda i: (named[i], page.depth[i], score[i], -i))
    while page.parent[best] and page.bar[best] <= page.depth[page.parent[best]] and count[page.parent[best]] > count[best]:
        best = page.parent[best]
    return best, max(score[best], 1.0)


def _within(page: Page, roots: set[int], depth: int) -> str:
    """The text below nodes of one depth, without what marked elements between hold."""
    inside = [False] * len(page.parent)
    for node in range(len(inside)):
        inside[node] = node in roots or (node > 0 and inside[page.parent[node]])
    return " ".join([text for node, bar, text, _ in page.blocks if inside[node] and bar <= depth])


def _nodes_at(page: Page, path: list[str]) -> set[int]:
    """The nodes whose path is that one."""
    depth, along = len(path), [True] + [False] * (len(page.parent) - 1)
    for node in range(1, len(along)):
        at = page.depth[node]
        along[node] = at <= depth and along[page.parent[node]] and page.place[node] == path[at - 1]
    return {node for node, on in enumerate(along) if on and page.depth[node] == depth}


def chosen_text(page: Page, best: int | None, path: str | None) -> str:
    """The text within the host's path where that lies above or below the page's best container and holds most of its text, else within the latter;
    of a page without any, the text within the path, or all there is."""
    host = path.split(">") if path else None
    if best is None:
        common = _within(page, _nodes_at(page, host), len(host)) if host else ""
        loose = " ".join([b[2] for b in page.blocks if not b[1]])
        return common or loose or " ".join([b[2] for b in page.blocks])
    own_path, depth = page.path(best), page.depth[best]
    own = _within(page, _nodes_at(page, own_path), depth)
    if host and host != own_path and (own_path[: len(host)] == host or host[:depth] == own_path):
        common = _within(page, _nodes_at(page, host), len(host))
        if len(common) >= MOST * len(own):
            return common
    return own


def main_text(html: str | None, path: str | None = None) -> str:
    """One page's text within the path, or within its own best container."""
    page = page_of(html or "")
    best = best_container(page)
    return chosen_text(page, best[0] if best else None, path)


_NODES = "parent array<int>, place array<string>, depth array<int>, node array<int>, bar array<int>, text array<string>"


def _parse(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
    ints, strings = pa.list_(pa.int32()), pa.list_(pa.string())
    for batch in batches:
        pages = [page_of(x.as_py() or "") for x in batch.column(2)]
        bests = [best_container(p) for p in pages]
        paths = pa.array([">".join(p.path(b[0])) if b else None for p, b in zip(pages, bests, strict=True)], pa.string())
        runs = [[(k, [b[2] for b in group]) for k, group in groupby(p.blocks, lambda b: b[:2])] for p in pages]
        yield pa.RecordBatch.from_arrays(
            [batch.column(0), batch.column(1), pa.array([host_of(u.as_py()) for u in batch.column(1)], pa.string()), paths,
             pa.array([b[0] if b else None for b in bests], pa.int32()), pa.array([b[1] if b else 0.0 for b in bests], pa.float64()),
             pa.array([p.parent for p in pages], ints), pa.array([p.place for p in pages], strings), pa.array([p.depth for p in pages], ints),
             pa.array([[k[0] for k, _ in r] for r in runs], ints), pa.array([[k[1] for k, _ in r] for r in runs], ints), pa.array([[" ".join(t) for _, t in r] for r in runs], strings)],
            ["page_id", "url", "host", "own", "best", "score", "parent", "place", "depth", "node", "bar", "text"],
        )


def _reread(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
    for batch in batches:
        texts = []
        for row in batch.select(["best", "path", "parent", "place", "depth", "node", "bar", "text"]).to_pylist():
            page = Page()
            page.parent, page.place, page.depth = row["parent"], row["place"], row["depth"]
            page.blocks = [(k, bar, t, 0) for k, bar, t in zip(row["node"], row["bar"], row["text"], strict=True)]
            texts.append(chosen_text(page, row["best"], row["path"]))
        yield pa.RecordBatch.from_arrays([batch.column(0), batch.column(1), pa.array(texts, pa.string())], ["page_id", "url", "text"])


def host_paths(parsed: DataFrame) -> DataFrame:
    """(host, path): the path most of a host's pages vote for; ties go to the path with the higher scores, then the first in order."""
    votes = parsed.where("own is not null").groupBy("host", F.col("own").alias("path")).agg(F.count("*").alias("pages"), F.round(F.sum("score"), 3).alias("score"))
    return votes.groupBy("host").agg(F.min_by("path", F.struct(-F.col("pages"), -F.col("score"), F.col("path"))).alias("path"))


def extract_pages(pages: DataFrame, host_rows: int = HOST_ROWS) -> DataFrame:
    """page_id, url, text, n_chars of every page. Null and empty html give empty texts; pages without a host share one; rows that repeat an id, or are equal, are pages of their own and
    vote each; ties are settled as in ``host_paths``; an empty table gives no rows; the whole html is parsed, once, in time linear in its length, however it nests;
    other columns are ignored. Host paths are broadcast up to ``host_rows`` rows and joined by shuffling beyond, with the same result."""
    own = pages.select(F.col("page_id").cast("long").alias("page_id"), "url", "html")
    parsed = materialise(own.mapInArrow(_parse, f"page_id long, url string, host string, own string, best int, score double, {_NODES}"), "parsed", "zstd")
    paths = materialise(host_paths(parsed), "host-paths")
    paths = F.broadcast(paths) if paths.count() <= host_rows else paths
    columns = ["page_id", "url", "best", "path", "parent", "place", "depth", "node", "bar", "text"]
    read = parsed.join(paths, "host", "left").select(*columns).mapInArrow(_reread, "page_id long, url string, text string")
    return read.select("page_id", "url", "text", F.length("text").cast("long").alias("n_chars"))


def op2_html_text(spark: SparkSession, sf_dir: str) -> DataFrame:
    return extract_pages(spark.read.parquet(f"{sf_dir}/pages.parquet"))
