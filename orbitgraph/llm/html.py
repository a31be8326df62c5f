"""Main text of web pages by tree scoring.

The page is parsed into a light tree. Every paragraph-like block gives points for its length and its commas to its
ancestors, the full points to its parent and less the farther up; a container's sum is discounted by the share of its
text that is link text. The best container is kept (the whole article where it stands in one), with siblings that score
well themselves, hold plain text with few links, or lie between kept ones. Blocks come out in page order, one line each.

Menus, footers, scripts, styles, hidden parts and form controls are cut by element or role. Class and id names are
evidence only: a name that says "no article" outright (sidebar, comments, advert) cuts its element, unless that holds
more than half of the page's text in paragraphs and no article element stands elsewhere (comments go at any size); a name that may mean anything (more, legal, tags), or a telling
word beside others that are none of layout, cuts it outside the article, or inside where it is mostly links.

Edge cases: null or empty html, or pages without text, give an empty string; unclosed and stray tags are tolerated,
nesting of any depth is walked without recursion; repeated rows are extracted one by one; an empty table gives an empty
result; null urls and ids are carried; other columns are carried where they don't clash with the result's names.
"""

from __future__ import annotations

import html as entities
import re
from collections.abc import Iterator

import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F
from pyspark.sql import types as T

# Element groups.
VOID = frozenset("area base br col embed hr img input link meta param source track wbr".split())
RAW = frozenset("script style textarea title noscript template iframe noframes xmp svg math object".split())
CUT = frozenset("nav footer head button select option dialog menu canvas audio video input label".split()) | RAW
BLOCKS = frozenset("address article blockquote body caption center dd details dir div dl dt figcaption h1 h2 h3 h4 h5 h6 header hgroup html li main ol p pre section summary table tbody td tfoot th thead tr ul".split())
SCORED = frozenset("p pre td li blockquote dd h2 h3 h4 h5 h6".split())
CONTAINERS = frozenset("article body blockquote center div main section td table tbody ul ol dl html".split())
CLOSED_BY_BLOCK = frozenset(("p",))
INLINE_BREAKS = frozenset(("br", "hr"))
SAME_CLOSE = {"li": frozenset(("ul", "ol", "menu", "dir")), "dt": frozenset(("dl",)), "dd": frozenset(("dl",)), "tr": frozenset(("table", "tbody", "thead", "tfoot")), "td": frozenset(("tr", "table")), "th": frozenset(("tr", "table")), "option": frozenset(("select",))}
FORMATTING = frozenset("a b big code em font i s small span strike strong sub sup u tt mark".split())
# Parts of class or id names. Outright no article:
NOISE = frozenset(
    "ad ads adv advert adverts advertisement advertising adbox adsense banner sponsor sponsored promo promotion promoted"
    " nav navbar navigation menu menubar breadcrumb breadcrumbs pager pagination toolbar topbar"
    " footer siteheader masthead sidebar aside widget widgets related recommended recommendations trending"
    " notice notices cookie cookies consent gdpr alert popup modal overlay newsletter subscribe subscription signup login paywall"
    " share sharing social sharebar tagcloud hidden".split()
)
# reader comments, whatever their share of the page:
COMMENTS = frozenset("comment comments commentlist disqus replies reply respond".split())
# that may mean anything:
DOUBTFUL = frozenset("more popular side rail foot discussion feedback tags print skip copyright legal disclaimer".split())
# words of layout, which leave a telling word beside them as it is:
LAYOUT = frozenset(
    "box block bar list wrap wrapper container section sections links link post posts item items area panel inner outer top left right"
    " bottom main page site global primary secondary header head unit slot col column row module div content text body article entry"
    " group holder zone region form thread count reader readers user users guest visitor visitors title inline sticky fixed mobile desktop small large first last the of and my".split()
)
GOOD = frozenset("article body content entry main page post text story blog".split())
ROLES = frozenset("navigation banner contentinfo complementary search form dialog alert alertdialog menu menubar toolbar".split())
TOKEN = re.compile(r"<!--.*?(?:-->|$)|<!\[CDATA\[.*?(?:\]\]>|$)|<[!?][^>]*>?|<(/?)([a-zA-Z][^\s/>\x00]*)((?:=\s*(?:\"[^\"]*\"|'[^']*')|[^>])*+)>", re.S)
ATTRIBUTE = re.compile(r"([^\s\"'>/=]+)(?:\s*=\s*(?:\"([^\"]*)\"|'([^']*)'|([^\s\"'=<>`]+)))?")
SOFT_CUT = frozenset("aside form fieldset header".split())  # elements that are no article unless they hold most of the page
HEADER_NAME = re.compile(r"(?:class|id)\s*=\s*[\"']?(?:[^\"'>]*[\s_-])?(?:header|head)(?:[\s\"'>]|$)", re.I)
SPACE = re.compile(r"\s+")
HARD, SOFT, DOUBT = 3, 2, 1  # no article for certain; unless it holds most of the page; if outside the article or mostly links


class Node:
    __slots__ = ("chars", "children", "commas", "core", "depth", "inside", "links", "noise", "parent", "points", "tag", "weight")

    def __init__(self, tag: str, parent: Node | None, noise: int = 0, weight: float = 0.0, inside: bool = False):
        self.tag, self.parent, self.noise, self.weight, self.inside = tag, parent, noise, weight, inside
        self.children: list[Node | str] = []
        self.points = 0.0
        self.chars = self.links = self.commas = 0
        self.core = False  # holds an article or main element with text
        self.depth = parent.depth + 1 if parent else 0


def _named(value: str) -> int:
    """What a class or id says: HARD for comments, SOFT for telling names, DOUBT for names that may mean anything."""
    worst = 0
    for name in value.split():
        parts = set(re.findall(r"[a-z]+", name))
        if parts & COMMENTS and parts <= COMMENTS | LAYOUT | NOISE | DOUBTFUL:
            return HARD
        if parts & NOISE:
            worst = max(worst, SOFT if parts <= NOISE | LAYOUT | DOUBTFUL else DOUBT)
        elif parts & (DOUBTFUL | COMMENTS):
            worst = max(worst, DOUBT)
    return worst


def _judge(tag: str, attributes: str) -> tuple[int, float, bool]:
    """How surely the element is no article, the weight its names give it, and whether they say that it is the article."""
    noise, weight, good = HARD if tag in CUT else SOFT if tag in SOFT_CUT else 0, 0.0, tag in ("article", "main")
    if noise == HARD or not attributes or attributes.isspace():
        return noise, weight, good
    for m in ATTRIBUTE.finditer(attributes):
        name, value = m[1].lower(), (m[2] or m[3] or m[4] or "").lower()
        if name == "hidden" or name == "aria-hidden" and value == "true" or name == "style" and re.search(r"display\s*:\s*none|visibility\s*:\s*hidden", value):
            noise = HARD
        elif name == "role" and value in ROLES:
            noise = HARD
        elif name in ("class", "id"):
            said = _named(value)
            if said:
                noise = max(noise, said if tag not in ("html", "body", "article", "main") else HARD if said == HARD and tag == "article" else 0)
                weight -= 25.0
            if set(re.findall(r"[a-z]+", value)) & GOOD:
                weight += 25.0
                good |= not said
    return noise, weight, good


class _Tree:
    """Builds the tree tag by tag; how many of each tag are open says at once whether an end tag can close anything."""

    def __init__(self) -> None:
        self.root = self.here = Node("html", None)
        self.open: dict[str, int] = {}

    def push(self, node: Node) -> None:
        self.here.children.append(node)
        self.here = node
        self.open[node.tag] = self.open.get(node.tag, 0) + 1

    def leave(self, target: Node) -> None:
        while self.here is not target:
            self.open[self.here.tag] -= 1
            self.here = self.here.parent  # type: ignore[assignment]

    def start(self, tag: str, attributes: str) -> None:
        if tag in VOID:
            if tag in INLINE_BREAKS:
                self.here.children.append(Node(tag, self.here))
            return
        if tag in BLOCKS:
            self.leave(_implied(self.here, tag, self.open))
        here = self.here
        if tag in ("html", "body") and here.tag in ("html", "body") and here.parent is None:
            return
        noise, weight, good = _judge(tag, attributes)
        if noise < SOFT and HEADER_NAME.search(attributes) and tag not in ("html", "body", "article", "main"):
            noise = SOFT
        if noise == SOFT and here.inside and (tag == "header" or HEADER_NAME.search(attributes)) and not (tag != "header" and _judge(tag, attributes)[0]):
            noise = 0  # a header inside the article belongs to it; one of the page does not
        self.push(Node(tag, here, noise, weight, here.inside or good))
        if attributes.rstrip().endswith("/") and tag not in BLOCKS:
            self.leave(here)

    def end(self, tag: str) -> None:
        if not self.open.get(tag):
            return
        up = self.here
        while up.tag != tag:
            if up.tag in BLOCKS and tag in FORMATTING or up.tag in CUT and tag not in CUT and tag not in ("body", "html"):
                return  # a stray end tag does not leave the block it stands in
            up = up.parent  # type: ignore[assignment]
        self.leave(up.parent if up.parent is not None else up)


def parse(page: str) -> Node:
    tree = _Tree()
    at, end = 0, len(page)
    for m in _tokens(page):
        if m.start() > at:
            tree.here.children.append(page[at : m.start()])
        at = m.end()
        if m[2] is None:
            continue
        if m[1]:
            tree.end(m[2].lower())
        else:
            tree.start(m[2].lower(), m[3] or "")
    if at < end:
        tree.here.children.append(page[at:])
    _weigh(tree.root)
    return tree.root


def _weigh(root: Node) -> None:
    """Characters, link characters and commas of every node without certain noise, bottom up; then what is in doubt is
    settled top down, and what turns out as noise is taken out of the counts."""
    order = [root]
    for node in order:
        order.extend(c for c in node.children if not isinstance(c, str) and c.noise != HARD)

    def count() -> None:
        for node in reversed(order):
            node.chars = node.links = node.commas = 0
            node.core = False
            for c in node.children:
                if isinstance(c, str):
                    if not c.isspace():
                        node.chars += len(c)
                        node.commas += c.count(",") + c.count("،") + c.count("、") + c.count("，")
                elif c.noise != HARD:
                    node.chars, node.links, node.commas = node.chars + c.chars, node.links + c.links, node.commas + c.commas
                    node.core |= c.core
            node.core |= node.tag in ("article", "main") and node.chars > 0
            if node.tag == "a":
                node.links = node.chars

    count()
    for node in order:
        if node.noise in (SOFT, DOUBT):
            holds_most = 2 * node.chars > root.chars and (node.core if root.core else _prose(node))
            spared = holds_most or node.noise == DOUBT and node.parent.inside  # type: ignore[union-attr]
            node.noise = 0 if spared and node.links * 2 <= node.chars else HARD
    count()


def _tokens(page: str) -> Iterator[re.Match]:
    """Tags and comments; what stands inside raw elements is skipped up to their end tag."""
    at = 0
    while m := TOKEN.search(page, at):
        yield m
        at = m.end()
        if m[2] and not m[1] and m[2].lower() in RAW and not (m[3] or "").rstrip().endswith("/"):
            close = re.compile(rf"</{re.escape(m[2])}\s*>", re.I).search(page, at)
            if close is None:
                if m[2].lower() in ("script", "style", "textarea", "title", "xmp"):
                    yield _Raw(at, len(page))
                    return
                continue
            yield _Raw(at, close.start())
            yield TOKEN.match(page, close.start())
            at = close.end()


class _Raw:
    """Stands for the inside of a raw element: no text, no tag."""

    def __init__(self, start: int, stop: int):
        self._start, self._stop = start, stop

    def start(self) -> int:
        return self._start

    def end(self) -> int:
        return self._stop

    def __getitem__(self, group: int) -> None:
        return None


def _implied(here: Node, tag: str, open_: dict[str, int]) -> Node:
    """Ends open paragraphs (through formatting) before a block, and open items before the next one of their list."""
    up = here
    while open_.get("p") and up.parent is not None and (up.tag in FORMATTING or up.tag == "p"):
        if up.tag == "p":
            return up.parent
        up = up.parent
    if tag in SAME_CLOSE and any(open_.get(t) for t in (("dt", "dd") if tag in ("dt", "dd") else ("td", "th") if tag in ("td", "th") else (tag,))):
        up = here
        while up.parent is not None and up.tag not in SAME_CLOSE[tag]:
            if up.tag == tag or tag in ("dt", "dd") and up.tag in ("dt", "dd") or tag in ("td", "th") and up.tag in ("td", "th"):
                return up.parent
            up = up.parent
    return here


def clean(text: str) -> str:
    return SPACE.sub(" ", entities.unescape(text) if "&" in text else text).strip()


def _walk(node: Node) -> Iterator[Node]:
    """Nodes in page order, noise left out."""
    stack = [node]
    while stack:
        node = stack.pop()
        yield node
        stack.extend(c for c in reversed(node.children) if not isinstance(c, str) and c.noise != HARD)


def _link_share(node: Node) -> float:
    return node.links / node.chars if node.chars else 0.0


def _prose(node: Node) -> bool:
    """Holds a paragraph, or text that ends like a sentence."""
    last = ""
    for n in _walk(node):
        if n.tag in ("p", "pre", "blockquote", "li", "dd", "td") and n.chars:
            return True
        last = next((c for c in reversed(n.children) if isinstance(c, str) and not c.isspace()), last)
    return last.rstrip()[-1:] in ".!?…:;»”\"'。！？"


def best_containers(root: Node) -> list[Node]:
    """The best-scoring container and the siblings worth keeping, in page order."""
    touched: dict[int, Node] = {}
    for node in _walk(root):
        own_text = node.tag in ("div", "section", "article", "main", "body", "html") and any(isinstance(c, str) and not c.isspace() for c in node.children)
        if node.tag not in SCORED and not own_text:
            continue
        if own_text:
            chars = sum(len(c) for c in node.children if isinstance(c, str) and not c.isspace())
            commas, up, level = sum(c.count(",") for c in node.children if isinstance(c, str)), node, 0
        else:
            chars, commas, up, level = node.chars, node.commas, node.parent, 0
        if chars < 20:
            continue
        points = 1 + commas + min(chars / 100, 3) + chars / 1000
        while up is not None and level < 5:
            if up.tag in CONTAINERS:
                up.points += points / (1 if level == 0 else 2 if level == 1 else level * 3)
                touched[id(up)] = up
            level += 1
            up = up.parent
    if not touched:
        return [root]

    def score(node: Node) -> float:
        bonus = 25.0 if node.tag in ("article", "main") else -3.0 if node.tag in ("ul", "ol", "dl") else 0.0
        return (node.points + node.weight + bonus) * (1 - _link_share(node))

    best = max(touched.values(), key=lambda n: (score(n), n.depth))
    up: Node | None = best
    while up is not None and up.tag not in ("article", "main"):
        up = up.parent
    best = up or best  # nothing of the article around it is dropped
    if best.parent is None:
        return [best]
    least, siblings = max(10.0, score(best) * 0.2), [c for c in best.parent.children if not isinstance(c, str) and c.noise != HARD]
    inner = best.parent.tag not in ("body", "html")

    def worth(node: Node) -> bool:
        if node is best or (id(node) in touched and score(node) >= least):
            return True
        plain = node.chars > 0 and _link_share(node) < 0.25
        return plain and (node.tag in ("p", "pre", "blockquote", "h1", "h2") or inner and _prose(node))

    kept = [i for i, node in enumerate(siblings) if worth(node)]
    between = lambda i: kept[0] < i < kept[-1] and siblings[i].chars > 0 and _link_share(siblings[i]) < 0.5
    chosen = set(kept)
    return [node for i, node in enumerate(siblings) if i in chosen or between(i)]


def blocks(nodes: list[Node]) -> list[str]:
    out: list[str] = []
    run: list[str] = []

    def flush() -> None:
        text = clean("".join(run))
        run.clear()
        if text:
            out.append(text)

    # a stack of what is still to come: a string, a node, or None for the end of a block
    for first in nodes:
        flush()
        stack: list[Node | str | None] = [first]
        while stack:
            item = stack.pop()
            if item is None:
                flush()
            elif isinstance(item, str):
                run.append(item)
            elif item.noise != HARD:
                if item.tag == "br":
                    run.append("\n")
                    continue
                if item.tag in BLOCKS or item.tag == "hr":
                    flush()
                    stack.append(None)
                stack.extend(reversed(item.children))
    flush()
    return out


def main_text(page: str | None) -> str:
    if not page:
        return ""
    return "\n".join(blocks(best_containers(parse(page))))


def extract(pages: DataFrame, html_col: str = "html") -> DataFrame:
    """``pages`` without the html, plus text and n_chars (replacing columns of those names)."""
    carried = [c for c in pages.columns if c not in (html_col, "text", "n_chars")]
    rows = pages.select(*carried, F.col(html_col).alias("__html"))
    schema = T.StructType([*(pages.schema[c] for c in carried), T.StructField("text", T.StringType()), T.StructField("n_chars", T.LongType())])

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in batches:
            texts = [main_text(page) for page in batch.column(len(carried)).to_pylist()]
            arrays = [batch.column(i) for i in range(len(carried))] + [pa.array(texts, pa.string()), pa.array(map(len, texts), pa.int64())]
            yield pa.RecordBatch.from_arrays(arrays, names=[*carried, "text", "n_chars"])

    return rows.mapInArrow(run, schema)
