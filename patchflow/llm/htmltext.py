"""Main text of web pages, with site template removal.

Pages are read by one scan over tags, with a stack of open elements.  Every element subtree is
hashed, Spark counts on how many pages of its host a hash stands, and subtrees on at least
``many`` pages and ``share`` of the host's pages are templates and are deleted.  An article
(``article``, ``main`` or role main) is the text itself and is never taken for a template as a whole.
What stands in it is counted apart, and must stand on ``share_inside`` of the pages, as a passage that
some articles quote is text; pages with equal articles count as one there, so that copies of a
page keep their text; inline elements amid text and table cells are parts of a sentence or row and go
or stay with it.  With no article the body is used.

What no count can tell, as it differs from page to page or its host has few pages, leaves by
its markup: elements that never are text (scripts, styles, forms ...) and, where ``named`` is set, those that name
themselves as furniture (nav, footer, aside, or such a word in class, id or role), like reader comments.

The recurring hashes are sent to the executors while they are at most ``most_hashes``; beyond that
each page gets its own by a join.

Null or empty html gives an empty text.  Broken and cut-off markup is read as far as it goes, very long
or deep pages without recursion.  Repeated rows each get their text; for the counts they are one page.
Null urls are one host.  Ties can't arise.  Other columns stay as they are; ``text`` is replaced.  An empty
table gives an empty one.
"""

from __future__ import annotations

import html as _html
import re
from collections.abc import Iterator

from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from .common import Scratch, as_bytes, fresh, map_arrow, read_table, sized_join
from .urlfilter import url_parts

ATTRIBUTES = r"""(?:[^>"']+|"[^"]*"|'[^']*')*"""
TOKEN = re.compile(rf"<!--.*?(?:-->|\Z)|<[!?][^>]*(?:>|\Z)|<(/?)([A-Za-z][A-Za-z0-9:-]*)(?:({ATTRIBUTES})>|([^>]*)(?:>|\Z))|</[^>]*(?:>|\Z)", re.S)
NAMED = re.compile(r"""(?:^|[\s"'/])(class|id|role|style|hidden|aria-hidden)\b(?:\s*=\s*("[^"]*"|'[^']*'|[^\s>]+))?""", re.I)
FURNITURE = re.compile(
    r"(?:^|[\s_-])(?:ads?|advert\w*|banner|sponsor\w*|promo\w*|cookies?|consent|gdpr|notice|alert|popup|modal|overlay|side-?bar|menu|nav|navbar|navigation|breadcrumbs?|comments?|replies|disqus|share|sharing|social|related|recommend\w*|newsletter|subscribe|sign-?up|login|footer|header|masthead|widget|toolbar|pagination|pager|search)(?:$|[\s_-])"
    r"|(?:^|\s)(?:navigation|complementary|contentinfo|search|dialog|alertdialog)(?:$|\s)",
    re.I,
)
LAYOUT = re.compile(r"(?:^|\s)(?:has|with|without|no|is|js|layout)[-_]\S*")
NOT_MAIN = re.compile(r"(?:^|\s)(?:comments?|comment-\w+|reply|replies|ads?|advert\w*|related|promo\w*|sponsor\w*|teaser)(?:$|\s)", re.I)
VOID = frozenset("area base br col embed hr img input link meta param source track wbr".split())
RAW = frozenset("script style textarea title xmp iframe noembed noframes".split())
DROPPED = frozenset("head script style noscript template iframe noembed noframes xmp object svg math canvas form button select option textarea input datalist nav header footer aside menu dialog title".split())
BLOCK = frozenset("address article aside blockquote body center dd details dialog dir div dl dt fieldset figcaption figure footer form h1 h2 h3 h4 h5 h6 header hgroup hr html legend li main menu nav ol p pre section summary table tbody td tfoot th thead tr ul".split())
#: An opening tag that ends an open element of its own sort, up to the border given.
ENDS = {"li": (("li",), ("ul", "ol", "menu")), "dt": (("dt", "dd"), ("dl",)), "dd": (("dt", "dd"), ("dl",)), "tr": (("tr",), ("table",)), "td": (("td", "th"), ("tr", "table")), "th": (("td", "th"), ("tr", "table")), "option": (("option",), ("select",))}
#: Parts of a row, which alone are no template.
CELLS = frozenset("td th".split())
ENDS_P = BLOCK - {"body", "html", "td", "th", "tr", "tbody", "thead", "tfoot", "li", "dd", "dt", "legend", "summary"}
SPACE = re.compile(r"\s+")


class Node:
    __slots__ = ("article", "children", "dropped", "name", "parent", "tag")

    def __init__(self, tag: str, name: str, parent, dropped: bool, article: bool):
        self.tag, self.name, self.parent, self.dropped, self.article, self.children = tag, name, parent, dropped, article, []


def _named(attributes: str) -> tuple[str, bool, bool]:
    """Class, id and role in one string; whether they say furniture or hidden; whether role is main."""
    said, out, main, lower = [], False, False, attributes.lower()
    for key, value in NAMED.findall(lower):
        value = value.strip("\"'")
        if key in ("class", "id", "role"):
            said.append(value)
            main |= key == "role" and value == "main"
        else:
            out |= key == "hidden" or key == "aria-hidden" and value == "true" or key == "style" and "display:none" in value.replace(" ", "")
    name = " ".join(said)
    return name, out or bool(name and FURNITURE.search(LAYOUT.sub(" ", name))), main


def parse(source: str, named: bool = True) -> Node:
    """The tree of a page: nodes and texts in order; ``named`` drops what names itself as furniture."""
    root = here = Node("#", "", None, False, False)
    at, n = 0, len(source)
    depth: dict[str, int] = {}

    def close(upto):
        nonlocal here
        while here is not upto:
            depth[here.tag] -= 1
            here = here.parent

    while at < n:
        found = TOKEN.search(source, at)
        if not found:
            here.children.append(source[at:])
            break
        if found.start() > at:
            here.children.append(source[at : found.start()])
        at = found.end()
        if found[2] is None:
            continue
        tag = found[2].lower()
        if found[1]:
            if depth.get(tag):
                up = here
                while up.tag != tag:
                    up = up.parent
                close(up.parent)
            elif tag in BLOCK:
                here.children.append(Node(tag, "", here, False, False))
            continue
        if tag in ENDS_P and depth.get("p"):
            up = here
            while up.tag != "p" and up.tag not in ("td", "th", "li", "button"):
                up = up.parent
            if up.tag == "p":
                close(up.parent)
        elif tag in ENDS:
            up, (mine, border) = here, ENDS[tag]
            while up.parent is not None and up.tag not in mine and up.tag not in border:
                up = up.parent
            if up.tag in mine:
                close(up.parent)
        attributes = found[3] if found[3] is not None else found[4]
        name, furniture, main = _named(attributes) if attributes else ("", False, False)
        furniture &= named
        article = tag in ("article", "main") or main
        if article:
            furniture = bool(name and NOT_MAIN.search(name))
            article = not furniture
        node = Node(tag, name, here, tag in DROPPED or furniture and tag not in ("html", "body"), article)
        here.children.append(node)
        if tag in RAW:
            end = re.compile(rf"</{tag}(?=[\s/>])[^>]*>?", re.I).search(source, at)
            at = end.end() if end else n
        elif tag not in VOID:
            here = node
            depth[tag] = depth.get(tag, 0) + 1
    return root


def _articles(root: Node) -> list[Node]:
    """Outermost articles in page order; those inside furniture only if there are no others."""
    for all_over in (False, True):
        out, stack = [], [root]
        while stack:
            node = stack.pop()
            if node.article:
                out.append(node)
            elif not node.dropped or all_over and node.tag not in DROPPED:
                stack.extend(c for c in reversed(node.children) if type(c) is Node)
        if out:
            return out
    return []


def subtree_hashes(root: Node) -> tuple[list[tuple[Node, int]], list[tuple[Node, int]], int]:
    """Hashes of the subtrees outside articles, those inside, and the hash of the articles themselves.

    Made from tag, name, text and the hashes below; without a stack limit.
    """
    import xxhash

    order, stack = [], [root]
    while stack:
        node = stack.pop()
        order.append(node)
        stack.extend(c for c in node.children if type(c) is Node)
    hashes: dict[int, int] = {}
    holds: set[int] = set()
    mixed: set[int] = set()
    for node in reversed(order):
        parts = [node.tag, node.name]
        inner = node.article
        said = False
        for c in node.children:
            if type(c) is Node:
                parts.append("%x" % hashes[id(c)])
                inner |= id(c) in holds
            else:
                parts.append(SPACE.sub(" ", c).strip())
                said |= bool(parts[-1])
        hashes[id(node)] = xxhash.xxh64_intdigest("\x1f".join(parts).encode("utf-8", "replace"))
        if inner:
            holds.add(id(node))
        if said:
            mixed.add(id(node))
    signed = lambda h: h - (1 << 64) if h >> 63 else h
    tops = _articles(root)
    top_ids = {id(t) for t in tops}
    body: set[int] = set()
    inside: set[int] = set()
    out, within = [], []
    for node in order:  # parents first
        up = id(node.parent)
        if node.article or up in inside:
            inside.add(id(node))
        if id(node) in top_ids or up in body:
            body.add(id(node))
        if not node.children or node.tag in ("#", "html", "body"):
            continue
        if id(node) in body:
            if id(node) not in top_ids and node.tag not in CELLS and (node.tag in BLOCK or up not in mixed):
                within.append((node, signed(xxhash.xxh64_intdigest(b"%x" % hashes[id(node)], 1))))
        elif id(node) not in inside and id(node) not in holds:
            out.append((node, signed(hashes[id(node)])))
    return out, within, signed(xxhash.xxh64_intdigest(" ".join("%x" % hashes[id(t)] for t in tops)))


def main_text(root: Node, deleted: set[int] = frozenset()) -> str:
    """Blocks of the article, or of the body, joined by two line feeds."""
    blocks: list[str] = []
    run: list[str] = []

    def flush():
        text = SPACE.sub(" ", "".join(run)).strip()
        if text:
            blocks.append(text)
        run.clear()

    for top in _articles(root) or [root]:
        stack: list = [(top, False)]
        while stack:
            x, done = stack.pop()
            if type(x) is str:
                run.append(_html.unescape(x) if "&" in x else x)
            elif x.tag in BLOCK:
                flush()
                if not done and not (x.dropped or id(x) in deleted):
                    stack.append((x, True))
                    stack.extend((c, False) for c in reversed(x.children))
            elif x.tag == "br":
                run.append(" ")
            elif not (x.dropped or id(x) in deleted):
                stack.extend((c, False) for c in reversed(x.children))
        flush()
    return "\n\n".join(blocks)


def _page_hashes(pages: DataFrame, by_page: bool = False) -> DataFrame:
    """(host, page, inside, hash): the distinct subtree hashes of each page; of those inside articles the page is the hash of its articles, unless ``by_page``."""

    def run(batches: Iterator):
        import pyarrow as pa

        for batch in batches:
            made = [subtree_hashes(parse(t.decode("utf-8", "replace"))) for t in as_bytes(batch.column(2))]
            lists = [pa.array([sorted({h for _, h in m[k]}) for m in made], pa.list_(pa.int64())) for k in (0, 1)]
            yield pa.RecordBatch.from_arrays([batch.column(0), batch.column(1), pa.array([m[2] for m in made], pa.int64()), *lists], ["host", "page", "article", "hashes", "within"])

    made = map_arrow(pages.select("host", "page", "html"), run, "host string, page long, article long, hashes array<long>, within array<long>")
    inside = F.struct(F.col("page" if by_page else "article").alias("page"), F.col("within").alias("hashes"), F.lit(True).alias("inside"))
    units = F.array(F.struct("page", "hashes", F.lit(False).alias("inside")), inside)
    return made.select("host", F.inline(units)).select("host", "page", "inside", F.explode("hashes").alias("hash"))


def _all_hashes(root: Node) -> list[tuple[Node, int]]:
    out, within, _ = subtree_hashes(root)
    return out + within


def extract(pages: DataFrame, many: int = 20, share: float = 0.05, share_inside: float = 0.25, most_hashes: int = 500_000, named: bool = True) -> DataFrame:
    """The rows (html left out) with ``text``; a column of that name is replaced."""
    spark = pages.sparkSession
    scratch = Scratch(spark, "html")
    html = F.col("html").cast("string")
    host, _ = url_parts(F.col("url").cast("string"))
    kept = [c for c in pages.columns if c not in ("html", "text")]
    c_host, c_page, c_html, c_seed, c_own = (fresh(c, pages.columns) for c in ("_host", "_page", "_html", "_seed", "_own"))
    keyed = pages.select(*[F.col(f"`{c}`") for c in kept], host.alias(c_host), F.xxhash64("url", html).alias(c_page), html.alias(c_html))
    paged = keyed.select(F.col(c_host).alias("host"), F.col(c_page).alias("page"), F.col(c_html).alias("html"))
    hashes = _page_hashes(paged)
    counts = hashes.groupBy("host", "inside", "hash").agg(F.count_distinct("page").alias("n")).filter(F.col("n") >= many)
    # hosts too small for the share to pass the floor need no size
    large = scratch.save(paged.select("host", "page").distinct().groupBy("host").agg(F.count("*").alias("pages")).filter(max(share, share_inside) * F.col("pages") > many))
    least = F.when(F.col("inside"), share_inside).otherwise(share) * F.coalesce("pages", F.lit(0))
    counts = sized_join(counts, large, ["host"], scratch, "left", rows=large.rows).filter(F.col("n") >= least)
    often = scratch.save(counts.select(F.xxhash64("host", "hash").alias("key"), "host", "hash"))
    if often.rows <= most_hashes:  # 8 bytes each
        shipped = spark.sparkContext.broadcast(frozenset(r[0] for r in often.select("key").collect()))
        rows = keyed.withColumn(c_seed, F.xxhash64(c_host))
        own = None
    else:
        held = _page_hashes(paged, by_page=True)
        per_page = held.join(often.hint("merge"), ["host", "hash"], "left_semi").groupBy(F.col("page").alias(c_page)).agg(F.collect_set("hash").alias(c_own))
        rows, shipped = keyed.join(per_page.hint("shuffle_hash"), c_page, "left"), None
        own = rows.columns.index(c_own)
    at = rows.columns.index(c_html)
    picks = [rows.columns.index(c) for c in kept]
    seed = rows.columns.index(c_seed) if shipped else None

    def run(batches: Iterator):
        import pyarrow as pa

        for batch in batches:
            texts = []
            for i, t in enumerate(as_bytes(batch.column(at))):
                root = parse(t.decode("utf-8", "replace"), named)
                if shipped is not None:
                    gone = set()
                    if shipped.value:
                        first = batch.column(seed)[i].as_py()
                        gone = {id(node) for node, h in _all_hashes(root) if spark_hash(h, first) in shipped.value}
                else:
                    mine = set(batch.column(own)[i].as_py() or ())
                    gone = {id(node) for node, h in _all_hashes(root) if h in mine} if mine else set()
                texts.append(main_text(root, gone))
            yield pa.RecordBatch.from_arrays([*(batch.column(k) for k in picks), pa.array(texts, pa.string())], [*kept, "text"])

    schema = rows.select(*[F.col(f"`{c}`") for c in kept]).schema.add("text", "string")
    return map_arrow(rows, run, schema)


def spark_hash(value: int, seed: int) -> int:
    """What Spark's xxhash64 makes of a long when the hash of the columns before is ``seed``: XXH64 of its 8 bytes."""
    import xxhash

    h = xxhash.xxh64_intdigest((value & (2**64 - 1)).to_bytes(8, "little"), seed & (2**64 - 1))
    return h - (1 << 64) if h >> 63 else h


def op7_html_text(spark, sf_dir: str) -> DataFrame:
    pages = read_table(spark, sf_dir, "pages").select("page_id", "url", "html")
    return extract(pages).select("page_id", "url", "text", F.length("text").cast("long").alias("n_chars"))
