"""Main text of web pages by consensus host paths.

Each page's containers are scored by the running text they hold; the best one's path of tags and classes, with digits and
long class values generalised, is the page's vote for its host. The votes are counted in Spark, and every page is then
extracted again from the container whose path won most votes on its host, or from its own best one where it has none such.
"""

from __future__ import annotations

import html as html_lib
import re
from collections.abc import Iterator

import pyarrow as pa
from pyspark.sql import DataFrame, Window
from pyspark.sql import functions as F

from neargraph.llm.kernels import record
from neargraph.runtime import Scratch, prepare

# Element kinds of the HTML format.
RAW = {"script", "style", "textarea", "title", "xmp", "noframes", "iframe", "noembed"}
VOID = {"area", "base", "br", "col", "embed", "hr", "img", "input", "link", "meta", "source", "track", "wbr", "param"}
BLOCK = {
    "address", "article", "aside", "blockquote", "body", "center", "dd", "details", "dialog", "dir", "div", "dl", "dt", "fieldset", "figcaption", "figure", "footer", "form", "h1", "h2", "h3", "h4", "h5", "h6",
    "header", "hgroup", "hr", "html", "li", "main", "menu", "nav", "ol", "p", "pre", "section", "summary", "table", "tbody", "td", "tfoot", "th", "thead", "tr", "ul", "caption", "head",
}
DROPPED = {"script", "style", "noscript", "template", "title", "head", "nav", "footer", "header", "aside", "form", "button", "select", "option", "input", "textarea", "iframe", "object", "canvas", "audio", "video", "menu", "dialog", "label", "fieldset", "noframes", "noembed", "xmp", "map"}
CONTAINERS = {"html", "article", "main", "section", "div", "td", "body", "blockquote"}
CLOSES_P = BLOCK - {"html", "head", "body"}
ITEMS = {"li": {"li"}, "dt": {"dt", "dd"}, "dd": {"dt", "dd"}, "tr": {"tr", "td", "th"}, "td": {"td", "th"}, "th": {"td", "th"}, "option": {"option"}}
#: Words of class, id or role names that mark what does not belong to the article.
NOISE = re.compile(
    r"(?:^|[\s_-])(?:ads?|adv|advert\w*|adsense|adbox|adslot|sponsor\w*|promo\w*|nav|navbar|navigation|menu|breadcrumbs?|sidebar|side-bar|aside|footer|masthead|site-header|page-header"
    r"|comments?|comment-list|commentlist|respond|disqus|replies|reply|reader-comments|related|recommend\w*|share|sharing|social|cookies?|consent|gdpr|notice|notices|popup|newsletter|subscribe|signup|login|pagination|pager|hidden|sr-only|skip-link)(?:$|[\s_-])",
    re.IGNORECASE,
)
#: Words that mark it only outside an article, as articles use them for their own parts too.
LOOSE_NOISE = re.compile(r"(?:^|[\s_-])(?:banner|foot|topbar|toolbar|alert|modal|overlay|widget|copyright|legal|disclaimer|tags)(?:$|[\s_-])", re.IGNORECASE)
#: Containers beyond which a path is not made longer.
PATH_DEPTH = 64
_TAG = re.compile(r"<(?:!--.*?(?:--!?>|$)|!\[CDATA\[.*?(?:\]\]>|$)|[!?][^>]*(?:>|$)|(/?)([a-zA-Z][^\s/>]*)((?:[^>\"']|\"[^\"]*\"|'[^']*')*)(?:>|$))", re.DOTALL)
_ATTRIBUTE = re.compile(r"([^\s=\"'<>/]+)(?:\s*=\s*(?:\"([^\"]*)\"|'([^']*)'|([^\s\"'>]+)))?")
_RAW_END = {t: re.compile(rf"</{t}(?=[\s/>])[^>]*>?", re.IGNORECASE) for t in RAW}
_SPACE = re.compile(r"\s+")
_HOST = re.compile(r"^[a-zA-Z][\w+.-]*://(?:[^/@?#]*@)?([^/:?#]*)")


class Node:
    """An element. ``box`` is the innermost container at or above it, ``article`` the innermost article or main."""

    __slots__ = ("article", "box", "children", "depth", "noise", "parent", "path", "tag")

    def __init__(self, tag: str, parent: Node | None, path: str, noise: bool, depth: int = 0) -> None:
        self.tag, self.parent, self.path, self.noise, self.depth = tag, parent, path, noise, depth
        self.children: list[Node | str] = []
        self.box = self if tag in CONTAINERS else parent.box if parent else None
        self.article = self if tag in ("article", "main") else parent.article if parent else None


def host_of(url: str | None) -> str:
    """Host of a URL in small letters, without ``www.`` and ``m.``; '' if there is none."""
    found = _HOST.match(url or "")
    host = found[1].lower() if found else ""
    return re.sub(r"^(?:www|m)\.", "", host)


def _generalise(names: str) -> str:
    """Class names in order, without digits and without values that no other page is likely to share."""
    kept = sorted({re.sub(r"\d+", "#", n.lower()) for n in names.split() if len(n) <= 30})
    return ".".join(kept[:3])


class _Tree:
    """The open elements: the innermost one, and how many of each tag there are, so that no search goes up in vain."""

    def __init__(self) -> None:
        self.root = self.node = Node("html", None, "html", False)
        self.open: dict[str, int] = {}

    def leave(self, node: Node) -> None:
        """Closes an element and all that is open in it."""
        while True:
            here, self.node = self.node, self.node.parent
            self.open[here.tag] -= 1
            if here is node:
                return

    def enter(self, tag: str, attributes: str) -> None:
        self.node = _open(self.node, tag, attributes)
        self.open[tag] = self.open.get(tag, 0) + 1

    def end(self, tag: str) -> None:
        """An end tag; a stray one is passed over."""
        if self.open.get(tag):
            up = self.node
            while up.tag != tag:
                up = up.parent
            self.leave(up)
        elif tag == "p":
            self.node.children.append(Node("p", self.node, self.node.path, self.node.noise))

    def close_implied(self, tag: str) -> None:
        """Leaves the paragraphs and items that the start of ``tag`` ends."""
        closing = ITEMS.get(tag, set()) | ({"p"} if tag in CLOSES_P else set())
        while any(map(self.open.get, closing)):
            up = self.node
            while up.parent is not None and up.tag not in closing and up.tag not in _SCOPE:
                up = up.parent
            if up.parent is None or up.tag not in closing:
                return
            self.leave(up)


def parse(source: str) -> Node:
    """A forgiving tree: unclosed paragraphs and items end where HTML ends them; a stray end tag is passed over."""
    tree = _Tree()
    at = 0
    pos = source.find("<")
    while pos >= 0:
        m = _TAG.match(source, pos)
        if m is None:  # a plain '<'
            pos = source.find("<", pos + 1)
            continue
        if pos > at:
            tree.node.children.append(source[at:pos])
        at = m.end()
        tag = m[2].lower() if m[2] else ""
        if tag and m[1]:
            tree.end(tag)
        elif tag == "head":
            tree.enter(tag, m[3])
        elif tag and tag != "html":
            if tag in CLOSES_P or tag in ITEMS:
                tree.close_implied(tag)
            if tree.node.tag == "head" and tag in BLOCK:
                tree.leave(tree.node)
            if tag in VOID or (m[3].rstrip().endswith("/") and tag in ("path", "circle", "rect")):
                tree.node.children.append(Node(tag, tree.node, tree.node.path, tree.node.noise))
            elif tag in RAW:
                end = _RAW_END[tag].search(source, at)
                at = end.end() if end else len(source)
            else:
                tree.enter(tag, m[3])
        pos = source.find("<", at)
    if at < len(source):
        tree.node.children.append(source[at:])
    return tree.root


#: Elements beyond which no open paragraph or item is looked for.
_SCOPE = {"table", "ul", "ol", "dl", "td", "th", "tr", "article", "body", "button", "div", "section", "main", "li", "dd", "dt", "blockquote"}


def _open(node: Node, tag: str, attributes: str) -> Node:
    noise, names = node.noise or tag in DROPPED, ""
    if tag == "header" and node.tag in ("article", "main"):
        noise = node.noise  # an article's own heading block
    if attributes.strip():
        values = {m[1].lower(): m[2] or m[3] or m[4] or "" for m in _ATTRIBUTE.finditer(attributes)}
        names = values.get("class", "")
        marks = f"{names} {values.get('id', '')} {values.get('role', '')}"
        if tag not in ("article", "main", "body", "html") and (NOISE.search(marks) or (node.article is None and LOOSE_NOISE.search(marks))):
            noise = True
        if "hidden" in values or values.get("aria-hidden") == "true" or "display:none" in values.get("style", "").replace(" ", ""):
            noise = True
    path, depth = node.path, node.depth
    if tag in CONTAINERS and depth < PATH_DEPTH:
        general = _generalise(names)
        path, depth = f"{path}>{tag}{'.' + general if general else ''}", depth + 1
    child = Node(tag, node, path, noise, depth)
    node.children.append(child)
    return child


def blocks(node: Node) -> list[str]:
    """Texts of the blocks below a node in page order, without what was marked as noise."""
    out: list[str] = []
    held: list[str] = []

    def end() -> None:
        if held:
            text = _SPACE.sub(" ", html_lib.unescape("".join(held))).strip()
            held.clear()
            if text:
                out.append(text)

    todo: list[Node | str | None] = list(reversed(node.children))
    while todo:
        item = todo.pop()
        if item is None:
            end()
        elif isinstance(item, str):
            held.append(item)
        elif item.tag == "br":
            held.append(" ")
        elif item.noise and not node.noise:
            if item.tag in BLOCK:
                end()
        else:
            if item.tag in BLOCK:
                end()
                todo.append(None)
            todo += reversed(item.children)
    end()
    return out


def best_container(root: Node) -> Node | None:
    """The container with the most running text of its own paragraphs: text, less what stands in links, a share of it handed up.

    A container inside an article stands for the whole article, so that its title and short sections are not lost.
    """
    scores: dict[int, list] = {}
    todo: list[tuple[Node, bool]] = [(root, False)]
    while todo:
        node, linked = todo.pop()
        if node.noise:
            continue
        linked = linked or node.tag == "a"
        own = 0
        for child in node.children:
            if isinstance(child, str):
                own += 0 if linked else len(child.strip())
            else:
                todo.append((child, linked))
        if own:
            up, share = node.box, 1.0
            while up is not None and share > 0.2:
                entry = scores.setdefault(id(up), [up, 0.0])
                entry[1] += own * share * (1.25 if up.tag in ("article", "main") else 1.0)
                share *= 0.7
                up = up.parent.box if up.parent else None
    if not scores:
        return None
    best = max(scores.values(), key=lambda e: e[1])[0]
    return best.article or best


def find_path(root: Node, path: str) -> list[Node]:
    """Topmost nodes with a path, in page order."""
    found, todo = [], [root]
    while todo:
        node = todo.pop()
        if node.noise:
            continue
        if node.path == path and node.tag in CONTAINERS:
            found.append(node)
        else:
            todo += [c for c in reversed(node.children) if isinstance(c, Node)]
    return found


def vote(source: str | None) -> str | None:
    """The generalised path of a page's best container."""
    best = best_container(parse(source)) if source else None
    return best.path if best is not None else None


def extract(source: str | None, paths: list[str]) -> str:
    """Text of the containers of the first path that holds text; of the page's own best container if none does."""
    if not source:
        return ""
    root = parse(source)
    for path in paths:
        if text := "\n\n".join(b for node in find_path(root, path) for b in blocks(node)):
            return text
    best = best_container(root)
    return "\n\n".join(blocks(best)) if best is not None else ""


def _host_votes(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
    schema = pa.schema([("host", pa.string()), ("path", pa.string()), ("n", pa.int64())])
    counts: dict[tuple[str, str], int] = {}

    def flush():
        keys = list(counts)
        return record(schema, [k[0] for k in keys], [k[1] for k in keys], list(counts.values()))

    for batch in batches:
        for url, source in zip(batch.column(0).to_pylist(), batch.column(1).to_pylist(), strict=True):
            if path := vote(source):
                key = (host_of(url), path)
                counts[key] = counts.get(key, 0) + 1
        if len(counts) > 100_000:
            yield flush()
            counts.clear()
    if counts:
        yield flush()


def host_paths(pages: DataFrame, *, keep: int = 3, least_share: float = 0.2) -> DataFrame:
    """``pages`` -> ``(host, paths)``: the paths with most votes on each host, most first, those of a fair share of its votes."""
    prepare(pages.sparkSession)
    votes = pages.select(F.col("url").cast("string").alias("url"), F.col("html").cast("string").alias("html")).mapInArrow(_host_votes, "host string, path string, n long")
    counted = votes.groupBy("host", "path").agg(F.sum("n").alias("n"))
    counted = Scratch(pages.sparkSession, "votes").keep(counted)
    # each host's best paths are picked before the rows are shuffled, so a host with many different paths costs no task more
    place = F.row_number().over(Window.partitionBy("host").orderBy(F.desc("n"), "path"))
    best = counted.withColumn("place", place).where(F.col("place") <= keep)
    whole = counted.groupBy("host").agg(F.sum("n").alias("all"))
    fair = best.join(whole, "host").where(F.col("n") >= F.col("all") * least_share)
    return fair.groupBy("host").agg(F.transform(F.array_sort(F.collect_list(F.struct("place", "path"))), lambda r: r["path"]).alias("paths"))


def _extract_batches(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
    schema = pa.schema([("page_id", pa.int64()), ("url", pa.string()), ("text", pa.string()), ("n_chars", pa.int64())])
    for batch in batches:
        ids, urls, sources, paths = (batch.column(i) for i in range(4))
        texts = [extract(s, p or []) for s, p in zip(sources.to_pylist(), paths.to_pylist(), strict=True)]
        yield record(schema, ids, urls, texts, [len(t) for t in texts])


#: Hosts whose winning paths are sent to every task; more hosts are joined by a shuffle.
BROADCAST_HOSTS = 20_000


def extract_pages(pages: DataFrame) -> DataFrame:
    """``pages`` -> ``(page_id, url, text, n_chars)``, one row for each page.

    A null or empty page gives ''. A null or odd URL belongs to the host ''. Repeated pages come back as often as they came
    and vote as often; on a tie of paths the smaller one wins. Blocks are joined by an empty line, white space inside a block becomes one space, and character references are decoded.
    """
    spark = prepare(pages.sparkSession)
    rows = pages.select(F.col("page_id").cast("long").alias("page_id"), F.col("url").cast("string").alias("url"), F.col("html").cast("string").alias("html"))
    paths = Scratch(spark, "hosts").keep(host_paths(pages))
    host = F.regexp_replace(F.lower(F.regexp_extract(F.coalesce("url", F.lit("")), r"^[a-zA-Z][\w+.-]*://(?:[^/@?#]*@)?([^/:?#]*)", 1)), r"^(?:www|m)\.", "")
    small = paths.count() <= BROADCAST_HOSTS
    side = paths.select(F.col("host").alias("path_host"), "paths")
    joined = rows.join(F.broadcast(side) if small else side, host == F.col("path_host"), "left").select("page_id", "url", "html", "paths")
    return joined.mapInArrow(_extract_batches, "page_id long, url string, text string, n_chars long")
