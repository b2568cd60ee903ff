"""Main text of web pages with site style trees.

The DOMs of one host are merged into a style tree: nodes with the same path of tags, classes and ids are one node.
A node's own importance is the entropy of its presentations (sequences of child tags) over the pages that have it, in units of the
largest possible entropy; the importance of its text is 1 minus the mean entropy of its text segments, so text that all
pages share weighs 0 and text of one page weighs 1. A node's composite importance mixes its own with its children's
(weight damping ** children). Branches that are below `threshold` with all that is in them are removed from each page of the host,
whatever their names; the tree knows nothing of elements and class words.

Entropy can't tell a menu that differs from page to page from content, so what the tree leaves is read with three priors (`roles`):
elements and roles of page furniture (menus, footers, forms, adverts ...) go; so do nodes with such words in classes and ids, unless they hold
the page's article or main element, a h1 of it, or more than half of its text outside removed branches (has-sidebar, comments-open stand on
wrappers of the content); and where the page has a main or a single article element, it is the page's text. Several articles
are it only if they hold a quarter of the text that the tree leaves, as teasers don't.

Each distinct page counts once for its host: a page whose html stands in k rows of the host adds 1/k of a page from each of them, so copies are not taken for
what all pages of the host share.

Merging is two distributed aggregates of counts (host, path, presentation or segment); pages of a host never meet in one
task. Nodes that stand on one page only have importance 1 and count for their parent by number alone, so that only one row per host and path of
two pages or more is put together to a tree.

Defined results: null or empty html is the empty text; a null url is a host of its own; a page whose host has no other page, or
only copies of it, has no tree and is read by the priors alone; unclosed and stray tags are mended as browsers do; comments and truncated pages are no error.
"""

from __future__ import annotations

import html
import math
import re

import pandas as pd
import pyarrow as pa
import xxhash
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F
from pyspark.sql import types as T

from .common import in_arrow, stored, table

DAMPING = 0.9
THRESHOLD = 0.15
#: Hosts and paths below the threshold that a broadcast may hold; beyond it they are joined by host.
BROADCAST_PATHS = 200_000
#: Repeated pages whose digests a broadcast may hold (about 40 bytes each); beyond it pages find their number of copies by a shuffled join.
BROADCAST_COPIES = 500_000
#: Keys that the copies of one page, or the pages of one host, are dealt to in joins.
SALTS = 16

# Element kinds of HTML.
VOID = frozenset("area base br col embed hr img input link meta param source track wbr".split())
INLINE = frozenset("a abbr acronym b bdi bdo big br cite code data del dfn em font i img ins kbd label mark q rp rt ruby s samp small span strike strong sub sup time tt u var wbr".split())
RAW = ("script", "style", "textarea", "title", "noscript", "iframe", "template", "xmp")
CLOSES_P = frozenset("address article aside blockquote center details dialog dir div dl fieldset figcaption figure footer form h1 h2 h3 h4 h5 h6 header hgroup hr main menu nav ol p pre search section table ul li dd dt tr td th".split())
SIBLINGS = {"li": {"li"}, "dt": {"dt", "dd"}, "dd": {"dt", "dd"}, "tr": {"tr", "td", "th"}, "td": {"td", "th"}, "th": {"td", "th"}, "option": {"option"}, "thead": {"tr", "td", "th"}, "tbody": {"tr", "td", "th", "thead", "tbody"}, "tfoot": {"tr", "td", "th", "tbody"}}
SCOPES = frozenset("article body div html main section table ul ol dl td th nav aside header footer form".split())
# Elements whose content is no text of the page; elements, roles and class words of page furniture.
SILENT = frozenset("script style noscript iframe template svg button select textarea input head title object embed canvas audio video".split())
FURNITURE = SILENT | frozenset("nav footer aside form header menu dialog label".split())
ROLES = frozenset("navigation banner contentinfo complementary search form dialog alert alertdialog menu menubar toolbar".split())
WORDS = frozenset("ad ads adv advert adverts advertisement advertising banner promo promoted promotion sponsor sponsored sponsors menu nav navbar navigation breadcrumb breadcrumbs sidebar aside footer header masthead cookie cookies consent gdpr notice notices popup modal overlay newsletter subscribe subscription signup login comment comments reply replies disqus related recommended share sharing social widget toolbar pagination pager skip".split())

_TOKEN = re.compile(rf"<!--.*?(?:-->|\Z)|<({'|'.join(RAW)})\b[^>]*>.*?(?:</\1\s*>|\Z)|<(/?)([a-zA-Z][a-zA-Z0-9:-]*)((?:\"[^\"]*\"|'[^']*'|[^'\">])*)(?:>|\Z)|<[!?/][^>]*(?:>|\Z)|[^<]+|<", re.S | re.I)
_ATTRIBUTE = re.compile(r"\b(class|id|role)\s*=\s*(?:\"([^\"]*)\"|'([^']*)'|([^\s\"'>]+))", re.I)
_HOST = re.compile(r"^(?:[a-zA-Z][a-zA-Z0-9+.-]*:)?//(?:[^/?#@]*@)?([^/?#:]*)")
_NAME = re.compile(r"[^.#]*")
_SPLIT = re.compile(r"[^a-z0-9]+")


def host_of(url: str | None) -> str:
    m = _HOST.match(url or "")
    return m[1].lower() if m else ""


class Node:
    __slots__ = ("tag", "path", "children", "furniture", "worded", "parent")

    def __init__(self, tag: str, path: str, parent, furniture: bool, worded: bool = False):
        self.tag, self.path, self.parent, self.furniture, self.worded, self.children = tag, path, parent, furniture, worded, []


def _label(tag: str, attributes: str, inside_article: bool) -> tuple[str, bool, bool]:
    """A node's name in its path, whether its element or role is page furniture, and whether its class or id says so. A header inside an article is content."""
    furniture = tag in FURNITURE and not (tag == "header" and inside_article)
    if "=" not in attributes:
        return tag, furniture, False
    name, worded = tag, False
    for key, a, b, c in _ATTRIBUTE.findall(attributes):
        value = (a or b or c).lower()
        if key.lower() == "role":
            furniture |= value in ROLES
        elif tag not in ("html", "body", "article", "main"):
            name += ("." if key.lower() == "class" else "#") + re.sub(r"\d+", "0", value).replace("/", "|")
            worded |= any(w in WORDS and not (w == "header" and inside_article) for w in _SPLIT.split(value))
    return name, furniture, worded


def parse(page: str) -> Node:
    """The page's DOM: nodes with their children, texts as strings among them."""
    root = Node("", "", None, False)
    at, articles = root, 0
    for m in _TOKEN.finditer(page):
        raw, closing, tag, attributes = m.groups()
        if tag is None:
            if raw is None and page[m.start()] != "<":
                at.children.append(m[0])
            elif raw is None and m[0] == "<":
                at.children.append("<")
            continue
        tag = tag.lower()
        if closing:
            if tag in VOID:
                if tag == "br":
                    at.children.append(" ")
                continue
            up = at
            while up is not root and up.tag != tag:
                if tag in INLINE and up.tag in SCOPES:
                    up = root
                    break
                up = up.parent
            if up is not root:
                while at is not up:
                    articles -= at.tag == "article"
                    at = at.parent
                articles -= at.tag == "article"
                at = at.parent
            continue
        if tag == "br":
            at.children.append(" ")
            continue
        ends = SIBLINGS.get(tag, set())
        if tag in CLOSES_P or ends:
            up, last = at, None
            while up is not root and (up.tag in INLINE or up.tag == "p" or up.tag in ends or up.tag not in SCOPES):
                if (up.tag == "p" and tag in CLOSES_P) or up.tag in ends:
                    last = up
                up = up.parent
            if last is not None:
                at = last.parent
        name, furniture, worded = _label(tag, attributes, articles > 0)
        node = Node(tag, f"{at.path}/{name}", at, furniture, worded)
        at.children.append(node)
        if tag not in VOID and not attributes.endswith("/"):
            at = node
            articles += tag == "article"
    return root


def segments(page: str):
    """(path, kind, value) of a page: 0 presence, 1 presentation, 2 text segment; each once. Elements without text of the page are left out with all in them."""
    found, stack = set(), [parse(page)]
    while stack:
        node = stack.pop()
        if node.tag in SILENT:
            continue
        found.add((node.path, 0, 0))
        tags = ",".join([c.tag for c in node.children if not isinstance(c, str)])
        found.add((node.path, 1, xxhash.xxh64_intdigest(tags) >> 1))
        for c in node.children:
            if not isinstance(c, str):
                stack.append(c)
            elif words := c.split():
                found.add((node.path, 2, xxhash.xxh64_intdigest(" ".join(words)) >> 1))
    return found


def _keep_wrappers(root: Node, low: frozenset) -> None:
    """Clears `worded` of nodes that hold the page's content: its article or main element, a h1 of it, or more than half of its text."""
    free, held, stack = [], [], [(root, False)]
    while stack:
        node, inside = stack.pop()
        if node.furniture or node.path in low:
            continue
        inside |= node.worded
        if node.tag == "main" or node.tag == "article":
            # articles in comments and teasers are not the page's where it has another
            (held if inside and node.tag == "article" else free).append(node)
        stack.extend((c, inside) for c in node.children if not isinstance(c, str))
    tops = {id(node) for node in free or held}
    nodes, above, holds, letters = [], [], [], []
    todo = [(root, -1, not tops)]
    while todo:
        node, up, inside = todo.pop()
        if node.furniture or node.path in low:
            continue
        top = id(node) in tops
        inside |= top
        todo.extend((c, len(nodes), inside) for c in node.children if not isinstance(c, str))
        nodes.append(node)
        above.append(up)
        holds.append(top or (inside and node.tag == "h1"))
        letters.append(sum(len(c.strip()) for c in node.children if isinstance(c, str)) if inside else 0)
    for i in range(len(nodes) - 1, 0, -1):  # parents stand before their children
        holds[above[i]] |= holds[i]
        letters[above[i]] += letters[i]
    for i, node in enumerate(nodes):
        if holds[i] or 2 * letters[i] > letters[0]:
            node.worded = False


def _letters(top: Node, low: frozenset) -> int:
    """Length of the text in a branch that stays."""
    n, stack = 0, [top]
    while stack:
        node = stack.pop()
        if isinstance(node, str):
            n += len(node.strip())
        elif not (node.furniture or node.worded or node.path in low):
            stack.extend(node.children)
    return n


def _without_roles(root: Node) -> None:
    """Leaves only what is no text at all marked as furniture."""
    stack = [root]
    while stack:
        node = stack.pop()
        node.furniture, node.worded = node.tag in SILENT, False
        stack.extend(c for c in node.children if not isinstance(c, str))


def main_text(page: str | None, low: frozenset = frozenset(), roles: bool = True) -> str:
    """The page's blocks in page order, joined by two line breaks, without branches in `low` and, with `roles`, without what the priors remove."""
    if not page:
        return ""
    root = parse(page)
    articles: list[Node] = []
    if roles:
        _keep_wrappers(root, low)
        stack = [root]
        while stack:
            node = stack.pop()
            if node.furniture or node.worded or node.path in low:
                continue
            if node.tag == "article" or node.tag == "main":
                articles.append(node)
                continue
            stack.extend(c for c in reversed(node.children) if not isinstance(c, str))
        if len(articles) > 1 and all(x.tag == "article" for x in articles) and 4 * sum(_letters(x, low) for x in articles) < _letters(root, low):
            articles = []
    else:
        _without_roles(root)
    blocks: list[str] = []
    current: list[str] = []

    def flush():
        if text := " ".join(html.unescape("".join(current)).split()):
            blocks.append(text)
        current.clear()

    for top in articles or [root]:
        work: list = [top]
        while work:
            node = work.pop()
            if node is None:
                flush()
            elif isinstance(node, str):
                current.append(node)
            elif not (node.furniture or node.worded or node.path in low):
                block = node.tag not in INLINE
                if block:
                    flush()
                    work.append(None)
                work.extend(reversed(node.children))
        flush()
    return "\n\n".join(blocks)


def _host(url: str):
    return F.lower(F.coalesce(F.regexp_extract(F.col(url).cast("string"), _HOST.pattern, 1), F.lit("")))


def _copied(pages: DataFrame, url: str, page: str) -> DataFrame:
    """url, html and copies of each page: the number of rows of its host with the same html. Only digests of pages are grouped."""
    text, host = F.col(page).cast("string"), _host(url)
    # two hashes of 64 bits, as the second starts from the page's own
    marked = pages.select(F.col(url).cast("string").alias("u"), text.alias("h"), F.xxhash64(host, text).alias("d"), F.xxhash64(text, host).alias("e"))
    repeated = stored(marked.filter("h <> ''").groupBy("d", "e").agg(F.count("*").alias("copies")).filter("copies > 1"), "page-copies")
    n = repeated.count()
    if not n:
        return marked.select("u", "h", F.lit(1).cast("long").alias("copies"))
    if n <= BROADCAST_COPIES:
        joined = marked.join(F.broadcast(repeated), ["d", "e"], "left")
    else:
        salted = marked.withColumn("salt", F.pmod(F.monotonically_increasing_id(), F.lit(SALTS)))
        joined = salted.join(repeated.withColumn("salt", F.explode(F.sequence(F.lit(0).cast("long"), F.lit(SALTS - 1).cast("long")))), ["d", "e", "salt"], "left")
    return joined.select("u", "h", F.coalesce("copies", F.lit(1).cast("long")).alias("copies"))


def style_tree(pages: DataFrame, url: str = "url", page: str = "html") -> DataFrame:
    """host, path, pages, own, content: the merged nodes of each host's distinct pages and their own importances."""

    def count(batches):
        held: dict[tuple, float] = {}

        def out():
            keys = list(held)
            columns = [pa.array([k[0] for k in keys], pa.string()), pa.array([k[1] for k in keys], pa.string()), pa.array([k[2] for k in keys], pa.int32()), pa.array([k[3] for k in keys], pa.int64()), pa.array(list(held.values()), pa.float64())]
            held.clear()
            return pa.RecordBatch.from_arrays(columns, ["host", "path", "kind", "value", "n"])

        for batch in batches:
            for u, h, copies in zip(*(c.to_pylist() for c in batch.columns), strict=True):
                if h:
                    host = host_of(u)
                    for path, kind, value in segments(h):
                        key = (host, path, kind, value)
                        held[key] = held.get(key, 0.0) + 1 / copies
                if len(held) > 100_000:
                    yield out()
        yield out()

    raw = in_arrow(_copied(pages, url, page), count, "host string, path string, kind int, value long, n double")
    # all copies of a page have the same nodes and texts, so the sums are whole numbers but for rounding
    each = raw.groupBy("host", "path", "kind", "value").agg(F.round(F.sum("n")).alias("n"))
    of = lambda k, x: F.coalesce(F.sum(F.when(F.col("kind") == k, x)), F.lit(0.0))
    n, spread = F.col("n"), F.col("n") * F.log(F.col("n"))
    sums = each.groupBy("host", "path").agg(of(0, n).alias("pages"), of(1, n).alias("n1"), of(1, spread).alias("s1"), of(2, n).alias("n2"), of(2, spread).alias("s2"))
    many = F.col("pages") > 1
    own = F.when(many, (F.log("n1") - F.col("s1") / F.col("n1")) / F.log("pages")).otherwise(1.0)
    content = F.when(F.col("n2") > 0, F.when(many, 1 - F.least(F.lit(1.0), F.col("s2") / F.col("n2") / F.log("pages"))).otherwise(1.0))
    return sums.select("host", "path", "pages", own.alias("own"), content.alias("content"))


def low_branches(tree: DataFrame, threshold: float = THRESHOLD, damping: float = DAMPING) -> DataFrame:
    """host, low: the paths of each host whose composite importance is below the threshold."""

    def judge(nodes: pd.DataFrame) -> pd.DataFrame:
        own = {r.path: r for r in nodes.itertuples()}
        children: dict[str, list[str]] = {}
        for path in own:
            if path:
                children.setdefault(path.rpartition("/")[0], []).append(path)
        worth: dict[str, float] = {}
        best: dict[str, float] = {}
        for path in sorted(own, key=lambda p: -p.count("/")):
            r = own[path]
            below = [(worth[c], own[c].pages) for c in children.get(path, ())]
            text = r.content if r.content is not None and not math.isnan(r.content) else None
            if text is not None:
                below.append((text, r.pages))
            if not below and not r.singles:
                worth[path] = best[path] = 1.0  # nothing in it, nothing to remove
                continue
            share = damping ** (len(below) + r.singles)
            mean = (sum(w * p for w, p in below) + r.singles) / (sum(p for _, p in below) + r.singles)
            worth[path] = max((1 - share) * r.own + share * mean, 0.0)
            best[path] = 1.0 if r.singles else max([worth[path], text or 0.0, *(best[c] for c in children.get(path, ()))])
        # emphasis and links within a text stay with it
        low = sorted(p for p, w in best.items() if w < threshold and _NAME.match(p.rpartition("/")[2])[0] not in INLINE)
        return pd.DataFrame({"host": nodes.host.iloc[:1], "low": [low]})

    # a node on one page only has importance 1, and so has all that is in it
    singles = tree.filter("pages <= 1").groupBy("host", F.regexp_replace("path", "/[^/]*$", "").alias("path")).agg(F.count("*").alias("singles"))
    shared = tree.filter("pages > 1").join(singles, ["host", "path"], "left").withColumn("singles", F.coalesce("singles", F.lit(0)))
    return shared.groupBy("host").applyInPandas(judge, "host string, low array<string>").filter(F.size("low") > 0)


def extract(pages: DataFrame, url: str = "url", page: str = "html", threshold: float = THRESHOLD, roles: bool = True) -> DataFrame:
    """pages with text and n_chars; columns of these names are replaced. threshold 0 is without the tree, roles=False without the priors."""
    low = stored(low_branches(stored(style_tree(pages, url, page), "style-tree"), threshold), "low-branches")
    names = [c for c in pages.columns if c not in ("text", "n_chars")]
    packed = pages.select(F.struct(*names).alias("row"), F.col(page).cast("string").alias("page"), _host(url).alias("host"))
    if (low.agg(F.sum(F.size("low"))).first()[0] or 0) <= BROADCAST_PATHS:
        joined = packed.join(F.broadcast(low), "host", "left").drop("host")
    else:
        # a host may have a third of all pages
        salts = F.explode(F.sequence(F.lit(0).cast("long"), F.lit(SALTS - 1).cast("long")))
        joined = packed.withColumn("salt", F.pmod(F.xxhash64("page"), F.lit(SALTS))).join(low.withColumn("salt", salts), ["host", "salt"], "left").drop("host", "salt")

    def run(batches):
        for batch in batches:
            texts, known = [], {}
            for h, paths in zip(batch.column("page").to_pylist(), batch.column("low").to_pylist(), strict=True):
                key = tuple(paths or ())
                texts.append(main_text(h, known.setdefault(key, frozenset(key)), roles))
            yield pa.RecordBatch.from_arrays([batch.column("row"), pa.array(texts, pa.string()), pa.array([len(t) for t in texts], pa.int64())], ["row", "text", "n_chars"])

    schema = T.StructType([joined.schema["row"], T.StructField("text", T.StringType()), T.StructField("n_chars", T.LongType())])
    return in_arrow(joined, run, schema).select("row.*", "text", "n_chars")


def op7_main_text(spark: SparkSession, sf_dir: str) -> DataFrame:
    """The main text of every page."""
    done = extract(table(spark, sf_dir, "pages").select("page_id", "url", "html"))
    return done.select("page_id", "url", "text", "n_chars")
