"""Main text of web pages by wrapper induction.

Pages are parsed into trees of block elements.  Their compact forms (labels, and hashes and lengths
in place of texts) are dealt by host, wherever a page was read, and every page is aligned by simple
tree matching with up to ``REFERENCES`` other pages of its host: the largest order-preserving
matching of equally labelled nodes, level by level, with runs of siblings of one shape folded into
one node.  Alignments give two votes, summed per host over the whole table:

* every aligned text slot votes constant where both pages say the same, varying where they differ;
* every element on the way to a varying text carries its length, and votes for being one of a kind
  among its siblings or not.

From the first come template slots.  From the second comes the content region of a host: the
deepest element that is one of a kind and carries most of the host's varying text.  A menu, an
advert or a footer may vary from page to page as the article does, but carries little of it.
Content is what lies in the region and is no template slot.  Names of elements and classes are a
prior on top: menus, page headers and footers, sidebars, notices, adverts, forms and comments are
template wherever they stand; inside what is named an article only near-certain votes make a slot
template; an element named so is content too where the region lies elsewhere.  ``names=False``
leaves all of these names aside.  Where a host has too few votes, those of all hosts decide.

A host's trees are dealt in parts of about ``DEALT`` pages, so hot hosts stay spread out; the two
passes over the pages shuffle compact trees but no html.
"""

from __future__ import annotations

import html
import pickle
import re
from collections import defaultdict
from collections.abc import Iterator
from urllib.parse import urlsplit

import pandas as pd
import xxhash
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from .common import Scratch

REFERENCES = 3
MIN_VOTES = 4
SURE_VOTES = 30
MAX_DECISIONS = 200_000
MAX_FOLDED = 200
DEALT = 1000
MAX_DEPTH = 120
MAX_SCOPE = 400
MIN_PAGES = 5
REGION_SHARE = 0.6

#: Element names and name parts; fixed values of the markup language and common usage.
_VOID = frozenset("area base br col embed hr img input link meta param source track wbr".split())
_SILENT = frozenset("script style noscript template head title svg math iframe object canvas audio video select button textarea datalist map".split())
_RAW = frozenset("script style textarea title noscript iframe xmp".split())
_INLINE = frozenset(
    "a abbr acronym b bdi bdo big cite code data del dfn em font i ins kbd label mark nobr output q rp rt ruby s samp small span strike strong sub sup time tt u var wbr img br input".split()
)
_CLOSES_P = frozenset(
    "address article aside blockquote center details dialog dir div dl fieldset figcaption figure footer form h1 h2 h3 h4 h5 h6 header hgroup hr main menu nav ol p pre section table ul li dd dt".split()
)
_SIBLING_ENDS = {"li": ("li",), "dt": ("dt", "dd"), "dd": ("dt", "dd"), "tr": ("tr", "td", "th"), "td": ("td", "th"), "th": ("td", "th"), "option": ("option",)}
_SCOPE = {"li": ("ul", "ol", "menu"), "dt": ("dl",), "dd": ("dl",), "tr": ("table",), "td": ("tr", "table"), "th": ("tr", "table"), "option": ("select",)}
_BOILER_TAGS = frozenset("nav footer aside form menu dialog".split())
_BOILER_ROLES = frozenset("navigation banner contentinfo complementary search form menu menubar alert dialog alertdialog".split())
_BOILER_WORDS = frozenset(
    "ad ads advert adverts advertisement advertising banner sponsor sponsored promo promoted promotion nav navbar navigation menu breadcrumb breadcrumbs"
    " sidebar footer masthead topbar cookie cookies consent notice notices gdpr popup modal overlay newsletter subscribe subscription signup login"
    " comment comments replies respond disqus discussion sharing social related recommended recommendations widget toolbar pagination pager"
    " skip alert".split()
)
#: Those that say so even beside a name for an article ("post-comments").
_FIRM_WORDS = frozenset("ad ads advert adverts comment comments replies respond sponsored promo related newsletter pagination breadcrumbs share sharing".split())
_ARTICLE_WORDS = frozenset("article articlebody post postbody entry story main maincontent".split())

_OTHER = r"<!--.*?(?:-->|$)|<!\[CDATA\[.*?(?:\]\]>|$)|<[!?][^>]*(?:>|$)"
_TAG = r"<(/?)([A-Za-z][^\s/>]*)"
_TOKEN = re.compile(_OTHER + "|" + _TAG + r"((?>\"[^\"]*\"|'[^']*'|[^'\">])*+)>|([^<]+|<)", re.S)
#: For what follows a quote that never ends: a tag goes to the next ">" there.
_LENIENT = re.compile(_OTHER + "|" + _TAG + r"([^>]*+)>|([^<]+|<)", re.S)
_OPENS = re.compile(r"</?[A-Za-z]")
_ATTR = re.compile(r"""\b(class|id|role|hidden|itemprop|aria-hidden)\b(?:\s*=\s*(?:"([^"]*)"|'([^']*)'|([^\s"'>]+)))?""", re.I)
_WORDS = re.compile(r"[a-z]+")
_SPACE = re.compile(r"\s+")


class Node:
    __slots__ = ("label", "tag", "children", "texts", "prior")

    def __init__(self, tag: str, label: str, prior: int):
        self.tag, self.label, self.prior = tag, label, prior
        self.children: list[Node] = []
        self.texts: list[tuple[int, str]] = []  # (block number, text) of the text directly in this node


BOILER, NEUTRAL, ARTICLE = -1, 0, 1


def _name(tag: str, attrs: str, above: Node, names_count: bool = True) -> tuple[str, int]:
    """Label and prior of an element; boilerplate holds for everything below it, article too unless boilerplate."""
    found = {k.lower(): (a or b or c or "") for k, a, b, c in _ATTR.findall(attrs)} if attrs else {}
    names = found.get("class", "") + " " + found.get("id", "")
    label = f"{tag}.{_SPACE.sub('.', names.strip().lower())}".replace("/", "|") if names.strip() else tag
    prior = above.prior
    if prior == BOILER or not names_count:
        return label, prior
    words = set(_WORDS.findall(names.lower()))
    named_article = bool(words & _ARTICLE_WORDS)
    role = found.get("role", "").lower()
    if tag in ("article", "main") or role in ("main", "article") or found.get("itemprop", "").lower() == "articlebody":
        if words & {"comment", "comments", "reply", "ad", "advert", "sponsored", "promo", "related"}:
            return label, BOILER
        return label, ARTICLE
    if tag == "body":
        return label, prior
    if tag in _BOILER_TAGS or role in _BOILER_ROLES or "hidden" in found or found.get("aria-hidden") == "true":
        return label, BOILER
    if tag == "header" and prior != ARTICLE:
        return label, BOILER
    if words & (_FIRM_WORDS if named_article else _BOILER_WORDS):
        return label, BOILER
    return label, ARTICLE if named_article else prior


def parse(source: str | None, names: bool = True) -> tuple[Node, list[tuple[str, str, int]]]:
    """The block tree of a page, and its text blocks in page order as (slot, text, prior).

    Elements deeper than ``MAX_DEPTH`` count as children of the one at that depth.
    """
    root = Node("", "", NEUTRAL)
    stack = [root]
    blocks: list[tuple[str, str, int]] = []
    text: list[str] = []
    silent = 0
    silent_tag = ""
    paths = {id(root): ""}

    def end_block() -> None:
        if text:
            own = _SPACE.sub(" ", html.unescape("".join(text))).strip()
            text.clear()
            if own:
                node = stack[-1]
                node.texts.append((len(blocks), own))
                blocks.append((paths[id(node)], own, node.prior))

    def near() -> range:
        """Open elements from the innermost outwards, so far as an end tag reaches."""
        return range(len(stack) - 1, max(0, len(stack) - 1 - MAX_SCOPE), -1)

    def open_node(tag: str, attrs: str) -> None:
        above = stack[min(len(stack), MAX_DEPTH) - 1]
        label, prior = _name(tag, attrs, stack[-1], names)
        node = Node(tag, label, prior)
        paths[id(node)] = f"{paths[id(above)]}/{label}"
        above.children.append(node)
        stack.append(node)

    at, size, token = 0, len(source or ""), _TOKEN
    while at < size:
        m = token.match(source, at)
        run = m.group(4)
        if run == "<" and _OPENS.match(source, at):
            # a tag that never ends: by an open quote, or because the page ends in it
            if token is _LENIENT:
                break
            token = _LENIENT
            continue
        at = m.end()
        if run is not None:
            if not silent:
                text.append(run)
            continue
        tag = m.group(2)
        if tag is None:
            continue
        tag = tag.lower()
        closing = bool(m.group(1))
        if silent:
            if tag == silent_tag:
                silent += -1 if closing else 1
            continue
        if tag in _SILENT:
            if closing or m.group(3).rstrip().endswith("/") and tag in ("svg", "math"):
                continue
            if tag in _RAW:
                stop = re.compile(rf"</{tag}\b[^>]*>", re.I).search(source, at)
                at = stop.end() if stop else size
                continue
            silent, silent_tag = 1, tag
            continue
        if tag in _INLINE:
            if tag in ("br", "img", "input"):
                text.append(" ")
            continue
        end_block()
        if tag in _VOID:
            continue
        if closing:
            for depth in near():
                if stack[depth].tag == tag:
                    del stack[depth:]
                    break
            continue
        if tag in _CLOSES_P:
            for depth in near():
                if stack[depth].tag == "p":
                    del stack[depth:]
                    break
                if stack[depth].tag in ("td", "th", "table", "button", "body"):
                    break
        for depth in near() if tag in _SIBLING_ENDS else ():
            if stack[depth].tag in _SIBLING_ENDS[tag]:
                del stack[depth:]
                break
            if stack[depth].tag in _SCOPE[tag]:
                break
        open_node(tag, m.group(3))
    end_block()
    return root, blocks


class Folded:
    """A node of the folded tree: siblings of one shape in a row are one node with all their texts."""

    __slots__ = ("label", "slot", "shape", "children", "texts", "chars", "folds")

    def __init__(self, node: Node, slot: str):
        self.label, self.slot = node.label, slot
        self.texts = {t for _, t in node.texts}
        self.chars, self.folds = sum(len(t) for _, t in node.texts), 1
        self.children: list[Folded] = []
        for child in node.children:
            own = Folded(child, f"{slot}/{child.label}")
            if self.children and self.children[-1].shape == own.shape:
                self.children[-1]._merge(own)
            else:
                self.children.append(own)
        self.shape = hash((self.label, tuple(c.shape for c in self.children)))

    def _merge(self, other: Folded) -> None:
        self.texts |= other.texts
        self.chars += other.chars
        self.folds += other.folds
        for a, b in zip(self.children, other.children, strict=True):
            a._merge(b)


def match(a: Folded, b: Folded) -> tuple[int, list[tuple[Folded, Folded]]]:
    """Size of the largest simple matching of two trees, and the matched nodes."""
    if a.label != b.label:
        return 0, []
    if not a.children or not b.children:
        return 1, [(a, b)]
    size, pairs = 1, [(a, b)]
    for x, y in _blocks(a.children, b.children):
        own, found = _aligned(x, y)
        size += own
        pairs += found
    return size, pairs


def _blocks(a: list[Folded], b: list[Folded]) -> Iterator[tuple[list[Folded], list[Folded]]]:
    """Two lists of siblings in parts of ``MAX_FOLDED`` at most: of longer ones equal ends go pair by pair, the rest in blocks."""
    if max(len(a), len(b)) > MAX_FOLDED:
        low, most = 0, min(len(a), len(b))
        while low < most and a[low].label == b[low].label:
            yield [a[low]], [b[low]]
            low += 1
        high = 0
        while high < most - low and a[-1 - high].label == b[-1 - high].label:
            yield [a[-1 - high]], [b[-1 - high]]
            high += 1
        a, b = a[low : len(a) - high], b[low : len(b) - high]
    for at in range(0, min(len(a), len(b)), MAX_FOLDED):
        yield a[at : at + MAX_FOLDED], b[at : at + MAX_FOLDED]


def _aligned(a: list[Folded], b: list[Folded]) -> tuple[int, list[tuple[Folded, Folded]]]:
    """Size of the largest order-preserving matching of two lists of siblings, and the matched nodes below them."""
    m, n = len(a), len(b)
    scores = [[match(x, y) for y in b] for x in a]
    most = [[0] * (n + 1) for _ in range(m + 1)]
    for i in range(m):
        for j in range(n):
            most[i + 1][j + 1] = max(most[i][j + 1], most[i + 1][j], most[i][j] + scores[i][j][0])
    pairs, i, j = [], m, n
    while i and j:
        if most[i][j] == most[i - 1][j]:
            i -= 1
        elif most[i][j] == most[i][j - 1]:
            j -= 1
        else:
            i, j = i - 1, j - 1
            pairs += scores[i][j][1]
    return most[m][n], pairs


def pack(tree: Folded) -> bytes:
    """The compact form of a tree: label, hashes and length of texts, folds and number of children of each node, in page order."""
    flat, stack = [], [tree]
    while stack:
        node = stack.pop()
        flat.append((node.label, tuple(sorted(xxhash.xxh64_intdigest(t.encode("utf-8", "surrogatepass")) for t in node.texts)), node.chars, node.folds, len(node.children)))
        stack += reversed(node.children)
    return pickle.dumps(flat, protocol=5)


def unpack(packed: bytes) -> Folded:
    """The tree of a compact form, with hashes in place of texts."""
    root, open_nodes = None, []
    for label, texts, chars, folds, n in pickle.loads(packed):
        node = Folded.__new__(Folded)
        node.label, node.texts, node.chars, node.folds, node.children = label, set(texts), chars, folds, []
        node.slot = f"{open_nodes[-1][0].slot}/{label}" if open_nodes else ""
        if open_nodes:
            open_nodes[-1][0].children.append(node)
            open_nodes[-1][1] -= 1
        else:
            root = node
        open_nodes.append([node, n])
        while open_nodes and not open_nodes[-1][1]:
            open_nodes.pop()
    return root


def host_of(url: str | None) -> str:
    try:
        return (urlsplit(url or "").hostname or "").lower()
    except ValueError:
        return ""


def _elements(tree: Folded) -> dict[str, bool]:
    """The slots of all elements of a page, and whether one of a kind stands there."""
    out: dict[str, bool] = {}
    stack = [tree]
    while stack:
        node = stack.pop()
        out[node.slot] = node.folds == 1 and node.slot not in out
        stack += node.children
    return out


_VOTES = "host string, slot string, prior int, same long, other long, mass long, single long, several long"
_ELEMENT = 9  # in place of a prior: votes on an element, not on a text slot


def votes(pages: DataFrame, names: bool = True) -> DataFrame:
    """(host, slot, prior, same, other, mass, single, several): the summed votes of all pages.

    Text slots have same and other (0 for slots never aligned).  Elements, with prior ``_ELEMENT``,
    have the length of the varying text they carry and the number of pages on which they are one of
    a kind, and not.  Pages with the same text blocks on one host vote as one.
    """

    def read(batches: Iterator[pd.DataFrame]) -> Iterator[pd.DataFrame]:
        for pdf in batches:
            rows = []
            for url, source in zip(pdf["url"], pdf["html"], strict=True):
                root, blocks = parse(source, names)
                if blocks:
                    texts = "\0".join(t for _, t, _ in blocks).encode("utf-8", "surrogatepass")
                    priors = {slot: prior for slot, _, prior in blocks}
                    rows.append((host_of(url), xxhash.xxh64_intdigest(texts) - (1 << 63), pack(Folded(root, "")), pickle.dumps(priors, protocol=5)))
            yield pd.DataFrame(rows, columns=["host", "body", "tree", "priors"])

    def align(batches: Iterator[pd.DataFrame]) -> Iterator[pd.DataFrame]:
        now, last = None, None
        held: list[Folded] = []
        for pdf in batches:
            tally: dict[tuple[str, str, int], list[int]] = defaultdict(lambda: [0] * 5)
            for host, part, body, packed, named in zip(pdf["host"], pdf["part"], pdf["body"], pdf["tree"], pdf["priors"], strict=True):
                if (host, part) != now:
                    now, last, held = (host, part), None, []
                priors = pickle.loads(named)
                for slot, prior in priors.items():
                    tally[host, slot, prior]  # a slot without votes is decided too, by all hosts
                if body == last:
                    continue
                last, tree = body, unpack(packed)
                elements = _elements(tree)
                for slot, one in elements.items():
                    tally[host, slot, _ELEMENT][3 if one else 4] += 1
                for other in held:
                    for x, y in match(tree, other)[1]:
                        if x.texts and y.texts and x.slot in priors:
                            tally[host, x.slot, priors[x.slot]][0 if x.texts == y.texts else 1] += 1
                            if x.texts != y.texts:
                                for depth, sign in enumerate(x.slot + "/"):
                                    if sign == "/":
                                        tally[host, x.slot[:depth], _ELEMENT][2] += x.chars
                if len(held) < REFERENCES:
                    held.append(tree)
            yield pd.DataFrame([(*k, *v) for k, v in tally.items()], columns=["host", "slot", "prior", "same", "other", "mass", "single", "several"])

    cast = pages.select(F.col("url").cast("string").alias("url"), F.col("html").cast("string").alias("html"))
    scratch = Scratch(pages.sparkSession, "trees")
    trees = scratch.keep(cast.mapInPandas(read, "host string, body long, tree binary, priors binary"))
    parts = trees.groupBy("host").agg(F.ceil(F.count("*") / DEALT).alias("parts"))
    dealt = trees.join(parts, "host").withColumn("part", F.pmod(F.xxhash64("body"), F.col("parts"))).drop("parts")
    dealt = dealt.repartition("host", "part").sortWithinPartitions("host", "part", "body", "tree")
    cast_votes = dealt.mapInPandas(align, _VOTES)
    return cast_votes.groupBy("host", "slot", "prior").agg(*[F.sum(c).alias(c) for c in ("same", "other", "mass", "single", "several")])


def wrapper(voted: DataFrame) -> DataFrame:
    """(host, slot) of the template slots that the prior alone would not call template.

    A host with enough votes on a slot decides it by its own; for any other host that has the
    slot, the votes of all hosts decide.
    """
    free = voted.where((F.col("prior") > BOILER) & (F.col("prior") != _ELEMENT)).select("host", "slot", "prior", "same", "other")
    every = free.groupBy("slot", "prior").agg(F.sum("same").alias("all_same"), F.sum("other").alias("all_other"))
    enough = F.when(F.col("prior") == NEUTRAL, MIN_VOTES).otherwise(SURE_VOTES)

    def template(same: str, other: str) -> F.Column:
        n = F.col(same) + F.col(other)
        return (n >= enough) & F.when(F.col("prior") == NEUTRAL, F.col(same) * 2 >= n).otherwise(F.col(same) * 20 >= n * 19)

    both = free.join(every, ["slot", "prior"])
    decided = F.when(F.col("same") + F.col("other") >= enough, template("same", "other")).otherwise(template("all_same", "all_other"))
    return both.where(decided).select("host", "slot").distinct()


def regions(voted: DataFrame) -> DataFrame:
    """(host, region): the slot of the element that holds the content of a host's pages, where one does.

    Of the elements that are one of a kind on nine pages of ten and carry ``REGION_SHARE`` of the
    varying text, which lie in each other, the deepest.  A host with pages fewer than ``MIN_PAGES``
    goes by the votes of all hosts on the elements that it has.
    """
    own = voted.where(F.col("prior") == _ELEMENT).select("host", "slot", "mass", "single", "several")
    every = own.groupBy("slot").agg(*[F.sum(c).alias(f"all_{c}") for c in ("mass", "single", "several")])
    whole = own.where("slot = ''").select("host", F.col("mass").alias("whole"), (F.col("single") + F.col("several")).alias("pages"))
    all_whole, all_pages = whole.agg(F.sum("whole"), F.sum("pages")).first()
    both = own.join(every, "slot").join(whole, "host")

    holds = (F.col("mass") >= F.col("whole") * REGION_SHARE) & (F.col("mass") > 0) & (F.col("single") >= F.col("several") * 9)
    # of all hosts, an element's share is that among the pages that have it
    shared = (F.lit(all_pages or 0) >= MIN_PAGES) & (F.col("all_mass") > 0) & (F.col("all_single") >= F.col("all_several") * 9)
    least = F.lit((all_whole or 0) * REGION_SHARE / max(1, all_pages or 0))
    shared = shared & (F.col("all_mass") >= least * (F.col("all_single") + F.col("all_several")))
    found = both.where(F.when((F.col("pages") >= MIN_PAGES) & (F.col("whole") > 0), holds).otherwise(shared))
    return found.groupBy("host").agg(F.max_by("slot", F.struct(F.length("slot"), "slot")).alias("region"))


def extract(pages: DataFrame, most: int = MAX_DECISIONS, names: bool = True) -> DataFrame:
    """(page_id, url, text, n_chars) of every page.

    A null or empty page, and one without content, give the empty text and 0.  A null or broken url
    belongs to the host without a name.  Repeated pages each give a row; a null page_id is kept; an
    empty table gives an empty result.  Up to ``most`` decisions are broadcast; more are joined, with
    the same result.  Without ``names``, element and class names say nothing, votes alone decide.
    Only page_id, url and html are read, so further columns cannot clash.
    """
    spark = pages.sparkSession
    scratch = Scratch(spark, "wrapper")
    voted = scratch.keep(votes(pages, names))
    own = pages.select("page_id", "url", F.col("html").cast("string").alias("html"))
    per_host = wrapper(voted).groupBy("host").agg(F.collect_set("slot").alias("slots"))
    per_host = scratch.keep(regions(voted).join(per_host, "host", "full"))
    if (per_host.agg(F.sum(F.coalesce(F.size("slots"), F.lit(0)) + 1)).first()[0] or 0) <= most:
        held = spark.sparkContext.broadcast({r["host"]: (r["region"], set(r["slots"] or ())) for r in per_host.toLocalIterator()})

        @F.pandas_udf("string")
        def main_text(urls: pd.Series, sources: pd.Series) -> pd.Series:
            rules = held.value
            return pd.Series([_text(s, *rules.get(host_of(u), (None, set())), names) for u, s in zip(urls, sources, strict=True)], dtype=object)

        out = own.withColumn("text", main_text(F.col("url").cast("string"), "html"))
    else:

        @F.pandas_udf("string")
        def hosts(urls: pd.Series) -> pd.Series:
            return pd.Series([host_of(u) for u in urls], dtype=object)

        @F.pandas_udf("string")
        def main_text_of(sources: pd.Series, where: pd.Series, slots: pd.Series) -> pd.Series:
            return pd.Series([_text(s, w, set() if x is None else set(x), names) for s, w, x in zip(sources, where, slots, strict=True)], dtype=object)

        out = own.withColumn("host", hosts(F.col("url").cast("string"))).join(per_host, "host", "left")
        out = out.withColumn("text", main_text_of("html", "region", "slots"))
    return out.select("page_id", "url", "text", F.length("text").cast("long").alias("n_chars"))


def _text(source: str | None, region: str | None, template: set[str], names: bool = True) -> str:
    """The content blocks of a page: those of the host's region and of what is named an article, else all that is not template."""
    _, blocks = parse(source, names)
    content = [(slot, text, prior) for slot, text, prior in blocks if prior > BOILER and slot not in template]
    inside = [c for c in content if c[2] == ARTICLE or region is not None and (c[0] + "/").startswith(region + "/")]
    return "\n".join(text for _, text, _ in inside or content)


def digest(pages: DataFrame) -> DataFrame:
    return extract(pages)
