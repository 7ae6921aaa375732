"""HTML extraction with a site style tree.

The pages of a host are merged: elements that stand under the same path of styles are one element node. The sequences of
children that pages show there are its style nodes (presentation), the texts that stand in it its content nodes. A node's
own importance is the entropy of its styles or contents over the pages, whichever is larger, as a share of the largest
entropy they could have: none if every page repeats one of them, all if each page has its own. A branch is as important as
the most important node in it, so one of low importance has nothing but low nodes. A content's importance is the share of
the pages with that node that do not repeat it.

What a page itself says of a part is a prior on the importance of the part and all below it: navigation, header, footer,
aside, form, advert, notice, comments - by element, role or name - weigh little, and so does what stands outside of the
articles of a page whose articles hold half of the text or more (they do not if they are cards of a list, say). Names do not
count for the page, its body, an article, or anything that holds an article. A text is kept if its importance - the least of
its branch, the branches above and the content itself - times the prior reaches LEAST_IMPORTANCE; this holds within articles
as outside. Nodes and contents that fewer than LEAST_PAGES pages of the host share count as important, so on small hosts the
priors decide.

Tables of the tree hold one row for each node, style or content of a host and page, combined before they are shuffled, and
branches are summed up over their ancestors by one aggregate, so no host is one task's work. The scores of the few nodes and
contents of lowered importance are broadcast within a checked size, and joined by host beyond it.
"""

from __future__ import annotations

import html
import re

import pyarrow as pa
import xxhash
from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

from .common import Scratch, batch_of, lookup, map_arrow

#: A text goes if its importance times the prior is lower; a node or content is judged if at least so many pages of the host
#: share it.
LEAST_IMPORTANCE, LEAST_PAGES = 0.2, 8
#: Prior of parts that name themselves, and of what stands outside of the articles of a page that consists of them.
PART_PRIOR = OUTSIDE_PRIOR = 0.15
#: Scores that are broadcast at most.
MOST_SCORES = 200_000

_TAG = re.compile(r"<!--.*?(?:-->|\Z)|<!\[CDATA\[.*?(?:\]\]>|\Z)|<[!?][^>]*(?:>|\Z)|<(/?)([a-zA-Z][^\s/>]*)((?:[^>\"']|\"[^\"]*(?:\"|\Z)|'[^']*(?:'|\Z))*)(?:>|\Z)", re.S)
_ATTR = re.compile(r"([^\s=/\"'>]+)(?:\s*=\s*(?:\"([^\"]*)\"?|'([^']*)'?|([^\s>]+)))?")
# fixed values: element names of HTML by their part in a page
_VOID = frozenset("area base br col embed hr img input link meta param source track wbr".split())
_RAW = frozenset("script style textarea title xmp iframe noembed noframes plaintext".split())
_INLINE = frozenset("a abbr acronym b bdi bdo big cite code data del dfn em font i ins kbd label mark meter nobr output progress q ruby rp rt s samp small span strike strong sub sup time tt u var wbr img picture source svg path".split())
_NO_TEXT = frozenset("script style noscript template head title iframe object embed applet input select textarea option svg canvas map audio video datalist".split())
_PARTS = frozenset("nav header footer aside form button dialog menu menuitem fieldset legend".split())
_MAIN = frozenset(("article", "main"))
_ROLES = frozenset("navigation banner contentinfo complementary search form dialog alert alertdialog menu menubar toolbar".split())
_NAMES = re.compile(r"(?:^|[\s_-])(?:ads?|adverts?|advertisements?|sponsor(?:ed)?|promo|banner|cookies?|consent|notice|popup|modal|newsletter|subscribe|nav|navbar|navigation|menu|breadcrumbs?|sidebar|footer|header|masthead|social|share|sharing|related|recommended|comments?|disqus|pagination|pager|widget|toolbar|skip)(?:$|[\s_-]|\d)", re.I)
# elements that an opening tag closes, and those it does not look beyond
_CLOSES = {"li": ({"li"}, {"ul", "ol", "menu"}), "dt": ({"dt", "dd"}, {"dl"}), "dd": ({"dt", "dd"}, {"dl"}), "tr": ({"tr", "td", "th"}, {"table"}), "td": ({"td", "th"}, {"tr", "table"}), "th": ({"td", "th"}, {"tr", "table"}), "option": ({"option"}, {"select"}), "thead": ({"tr", "td", "th"}, {"table"}), "tbody": ({"thead", "tbody", "tr", "td", "th"}, {"table"}), "tfoot": ({"tbody", "tr", "td", "th"}, {"table"})}
_ENDS_P = frozenset("address article aside blockquote center details dialog dir div dl fieldset figcaption figure footer form h1 h2 h3 h4 h5 h6 header hgroup hr main menu nav ol p pre section table ul".split())


class Node:
    __slots__ = ("children", "main", "named", "out", "part", "style", "tag")

    def __init__(self, tag: str, style: str = "", out: bool = False, main: bool = False, part: bool = False, named: bool = False):
        self.tag, self.style, self.out, self.main, self.part, self.named, self.children = tag, style, out, main, part, named, []


def _element(tag: str, attrs: str) -> Node:
    got = {m[1].lower(): html.unescape(next((x for x in m.groups()[1:] if x is not None), "")) for m in _ATTR.finditer(attrs)} if attrs.strip(" /\n\t") else {}
    name, role = f"{got.get('class', '')} {got.get('id', '')}".strip(), got.get("role", "").lower()
    out = tag in _NO_TEXT or "hidden" in got or got.get("aria-hidden") == "true" or "display:none" in got.get("style", "").replace(" ", "")
    main = tag in _MAIN or role in ("main", "article")
    return Node(tag, f"{tag}.{got.get('class', '')}", out, main, tag in _PARTS or role in _ROLES, bool(name and _NAMES.search(name)))


def parse(text: str) -> Node:
    """The element tree of a page; texts are strings among the children, with references decoded. Tolerates unclosed and
    stray tags: an end tag without its start is passed over, and blocks end an open paragraph."""
    root = Node("#root")
    stack, at = [root], 0
    for m in iter(lambda: _TAG.search(text, at), None):
        if m.start() > at:
            stack[-1].children.append(html.unescape(text[at : m.start()]))
        at = m.end() if m.end() > m.start() else m.end() + 1
        if not m[2]:
            if m[0].startswith("<![CDATA["):
                stack[-1].children.append(m[0][9:].removesuffix("]]>"))
            continue
        tag = m[2].lower()
        if m[1]:
            for i in range(len(stack) - 1, 0, -1):
                if stack[i].tag == tag:
                    del stack[i:]
                    break
                if stack[i].tag in ("td", "th", "table", "article", "main", "nav", "aside", "footer", "header", "form") and tag in _INLINE | {"p", "li"}:
                    break
            else:
                if tag == "p":
                    stack[-1].children.append(Node("p", "p."))
            continue
        if tag in _ENDS_P:
            for i in range(len(stack) - 1, 0, -1):
                if stack[i].tag == "p":
                    del stack[i:]
                    break
                if stack[i].tag not in _INLINE:
                    break
        if tag in _CLOSES:
            ends, stop = _CLOSES[tag]
            for i in range(len(stack) - 1, 0, -1):
                if stack[i].tag in stop:
                    break
                if stack[i].tag in ends:
                    del stack[i:]
        node = _element(tag, m[3])
        stack[-1].children.append(node)
        if tag in _VOID or m[3].endswith("/"):
            continue
        if tag in _RAW:
            end = re.compile(rf"</{tag}\b[^>]*(?:>|\Z)", re.I).search(text, at)
            node.children.append(text[at : end.start() if end else len(text)])
            at = end.end() if end else len(text)
            continue
        stack.append(node)
    if at < len(text):
        stack[-1].children.append(html.unescape(text[at:]))
    return root


def key_of(text: str) -> int:
    return xxhash.xxh64_intdigest(text.encode("utf-8", "surrogatepass")) - (1 << 63)


def _hold_main(root: Node) -> set[int]:
    """Nodes (by identity) that are an article or hold one; articles within parts do not count."""
    found: set[int] = set()
    stack: list = [(root, ())]
    while stack:
        node, above = stack.pop()
        if node.main:
            found.update((id(node), *above))
        if not node.out and not node.part:
            chain = (*above, id(node))
            stack.extend((c, chain) for c in node.children if isinstance(c, Node) and id(c) not in found)
    return found


def _own_text(node: Node) -> str:
    return " ".join(" ".join(c for c in node.children if isinstance(c, str)).split())


def text_blocks(root: Node, scores: dict[int, float] | None = None) -> list[str]:
    """Blocks of text in page order. scores: importance of paths and of (path, content) keys where it is low;
    None turns the tree off: every text then counts as important and no prior is asked."""
    held = _hold_main(root)
    blocks: list[tuple[str, bool]] = []
    open_: list[str] = []
    inside_now = False

    def close():
        line = " ".join("".join(open_).split())
        open_.clear()
        if line:
            blocks.append((line, inside_now))

    low = lambda worth: scores is not None and worth < LEAST_IMPORTANCE
    # (node, path, prior, importance of the branches above, inside an article, text taken); None closes a block
    stack: list = [(root, "", 1.0, 1.0, False, True)]
    while stack:
        item = stack.pop()
        if item is None:
            close()
            continue
        node, path, prior, worth, inside, take = item
        if isinstance(node, str):
            if take:
                open_.append(node)
            continue
        inline = node.tag in _INLINE
        if node.out:
            if not inline:
                stack.append(None)
            continue
        path = f"{path}/{node.style}"
        if node.part or node.named and id(node) not in held and node.tag not in ("html", "body"):
            prior = min(prior, PART_PRIOR)
        if scores is not None:
            worth = min(worth, scores.get(key_of(path), 1.0))
        if node.tag in ("br", "hr"):
            close()
            continue
        if not inline:
            close()
            stack.append(None)
        own = worth
        if scores and any(isinstance(c, str) for c in node.children):
            own = min(worth, scores.get(key_of(f"{path}\n{_own_text(node)}"), 1.0))
        inside = inside or node.main
        if not inline:
            inside_now = inside
        take = not low(own * prior)
        stack.extend((c, path, prior, worth, inside, take) for c in reversed(node.children))
    close()
    main = sum(len(t) for t, i in blocks if i)
    outside = OUTSIDE_PRIOR if main and 2 * main >= sum(len(t) for t, _ in blocks) else 1.0
    return [t for t, i in blocks if i or not low(outside)]


def tree_rows(root: Node) -> set[tuple[int, tuple[int, ...], int, int]]:
    """(path, paths above, kind, value) of the nodes of a page, as keys: kind 0 for each node, 1 for the sequence of its
    children's styles, 2 for its own text."""
    rows, stack = set(), [(root, "", ())]
    while stack:
        node, path, above = stack.pop()
        path = f"{path}/{node.style}"
        key = key_of(path)
        rows.add((key, above, 0, 0))
        inner = [c for c in node.children if isinstance(c, Node) and not c.out]
        if inner:
            rows.add((key, above, 1, key_of("|".join(c.style for c in inner))))
            stack.extend((c, path, (*above, key)) for c in inner)
        words = _own_text(node)
        if words or not inner:
            rows.add((key, above, 2, key_of(f"{path}\n{words}")))
    return rows


def host() -> Column:
    """Host of the column url, lower-case; empty if there is none."""
    return F.coalesce(F.lower(F.regexp_extract("url", r"^[A-Za-z][A-Za-z0-9+.-]*://(?:[^/?#@]*@)?([^/?#:]*)", 1)), F.lit(""))


def node_scores(pages: DataFrame, scratch: Scratch) -> DataFrame:
    """(host, key, score) of the nodes and contents whose importance lets them go under any prior; from all pages
    (url, html)."""

    def fn(batch: pa.RecordBatch):
        seen: dict[tuple, int] = {}
        for site, text in zip(batch.column(0).to_pylist(), batch.column(1).to_pylist(), strict=True):
            for row in tree_rows(parse(text or "")):
                seen[site, row] = seen.get((site, row), 0) + 1
        if seen:
            sites, rows = zip(*seen, strict=True)
            path, above, kind, value = zip(*rows, strict=True)
            yield batch_of({"host": pa.array(sites, pa.string()), "path": pa.array(path, pa.int64()), "above": pa.array([list(x) for x in above], pa.list_(pa.int64())), "kind": pa.array(kind, pa.int32()), "value": pa.array(value, pa.int64()), "n": pa.array(list(seen.values()), pa.int64())})

    rows = map_arrow(pages.select(host().alias("host"), "html"), fn, "host string, path long, above array<long>, kind int, value long, n long")
    per_value = scratch.save(rows.groupBy("host", "path", "kind", "value").agg(F.sum("n").alias("n"), F.first("above").alias("above")))
    nodes = per_value.where("kind = 0").select("host", "path", "above", F.col("n").alias("n_pages")).where(F.col("n_pages") >= LEAST_PAGES)
    # entropy from sums that are combined before the shuffle: H = log N - sum(n log n) / N, of log N at most
    total = F.sum("n")
    share = F.when(total > 1, (F.log(total) - F.sum(F.col("n") * F.log("n")) / total) / F.log(total)).otherwise(1.0)
    own = per_value.where("kind > 0").groupBy("host", "path", "kind").agg(share.alias("own")).groupBy("host", "path").agg(F.max("own").alias("own"))
    # each node counts for itself and for every branch it is in; nodes of few pages count as important
    rare = per_value.where("kind = 0").where(F.col("n") < LEAST_PAGES).select("host", "path", "above", F.lit(1.0).alias("own"))
    judged = nodes.join(own, ["host", "path"]).select("host", "path", "above", "own").unionByName(rare)
    branches = judged.select("host", "own", F.explode(F.concat(F.array("path"), "above")).alias("key")).groupBy("host", "key").agg(F.max("own").alias("score"))
    texts = per_value.where("kind = 2").where(F.col("n") >= LEAST_PAGES).select("host", "path", F.col("value").alias("key"), "n").join(nodes, ["host", "path"])
    contents = texts.select("host", "key", (1 - F.col("n") / F.col("n_pages")).alias("score"))
    return scratch.save(branches.unionByName(contents).where(F.col("score") < LEAST_IMPORTANCE))


def extract_main_text(pages: DataFrame, id_col: str = "page_id", url_col: str = "url", html_col: str = "html", tree: bool = True) -> DataFrame:
    """(page_id, url, text, n_chars) for every row of pages.

    text joins the blocks of the page's main part by empty lines; references are decoded, white space within a block is
    one space. Null and empty pages have an empty text; pages of any length are read whole. Pages without a host, or with a
    null url, are one site of their own. Rows with equal or null ids stay rows of their own; other columns are ignored; an
    empty table gives an empty result. tree=False leaves the style tree, and with it all judgement, out.
    """
    spark = pages.sparkSession
    scratch = Scratch(spark, "html")
    rows = pages.select(F.col(id_col).alias("page_id"), F.col(url_col).cast("string").alias("url"), F.col(html_col).cast("string").alias("html"))
    sent = scores = None
    dealt = rows.withColumn("host", host()).select("page_id", "url", "html", "host", F.lit(None).cast("map<long,double>").alias("scores"))
    if tree:
        scores = node_scores(rows, scratch)
        if scores.count() <= MOST_SCORES:
            found: dict[str, dict[int, float]] = {}
            for r in scores.collect():  # no more than MOST_SCORES
                found.setdefault(r["host"], {})[r["key"]] = r["score"]
            sent = spark.sparkContext.broadcast(found)
        else:
            keyed = rows.withColumn("host", host())
            sizes = keyed.groupBy("host").agg(F.count("*").alias("n"))
            per_host = scores.groupBy("host").agg(F.map_from_entries(F.collect_list(F.struct("key", "score"))).alias("scores")).join(sizes, "host")
            dealt = lookup(keyed, scratch.save(per_host), ["host"], "n", rows.count()).select("page_id", "url", "html", "host", "scores")

    def fn(batch: pa.RecordBatch):
        texts = []
        for page, site, mine in zip(*(batch.column(i).to_pylist() for i in (2, 3, 4)), strict=True):
            known = None if not tree else sent.value.get(site, {}) if sent is not None else dict(mine or ())
            texts.append("\n\n".join(text_blocks(parse(page or ""), known)))
        yield batch_of({"page_id": batch.column(0), "url": batch.column(1), "text": pa.array(texts, pa.string()), "n_chars": pa.array([len(t) for t in texts], pa.int64())})

    kind = rows.schema["page_id"].dataType.simpleString()
    return map_arrow(dealt, fn, f"page_id {kind}, url string, text string, n_chars long", 128)
