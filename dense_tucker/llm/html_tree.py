"""Main text of web pages by site style trees.

Every page is parsed once into elements and text blocks. A node's place is the chain of block elements above it with
their classes; the pages of a host are merged into one tree, in which copies of a page (equal main text) count once. An
element is important where its presentations (sequences of children) differ from page to page, a content
node where its contents do (entropies in units of the pages that have the node). Composite importance goes from the leaves up: an
element's own presentation counts 1 - DECAY ** presentations, its children's mean composite importance the rest.
A branch weighs its text, less what recurs, times its composite importance. The main path of a host goes from the root to the child
box that holds over half of its parent's weight, as far as there is one. Branches that leave it are the less important the less of
their parent's weight they hold; inside its last element contents that recur are unimportant. So each place has log odds from the tree,
counted the more the more pages bear it (PRIOR_PAGES). What a block's elements say of themselves (article, nav, class="ad", ...) is a
prior in log odds that the tree outvotes on hosts with enough pages; blocks with negative odds go, all others are joined in page order.

Two rules hold for a page as a whole: marked main text goes only where the page keeps at least as much other text, and names
alone do not empty a page (blocks named as noise return where nothing else stays, noise by element never).
An article or main element inside a wrapper named as noise is main text where the page has none elsewhere.

Nothing is gathered by host: all statistics are sums by place, and a page gets the odds of its own places, by its host and the set of
its places. Elements deeper than MAX_DEPTH count as their ancestor at that depth (their text stays).
White space inside a block is one space; a line break inside a block is white space. Null and empty html
give an empty text; a cut-off tag or comment at the end is no text; pages without url share a host of their
own; repeated rows are extracted one by one; an empty table gives an empty result; other columns are ignored.
"""

from __future__ import annotations

import html as entities
import re
from collections import Counter
from dataclasses import dataclass, field

import pyarrow as pa
import xxhash
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from .common import BROADCAST_ROWS, discard, materialise, slices

#: The tree's odds of a place on n pages count n / (n + PRIOR_PAGES).
PRIOR_PAGES = 3
DECAY = 0.9
MAX_DEPTH = 16
#: Log odds of what elements say: noise by element, by name, unnamed beside main text, unnamed, main by name, main by element, and a first heading's more.
NEVER, NAMED, BESIDE, PLAIN, LIKE, MAIN, HEADING = -3.0, -2.5, -0.5, 0.5, 1.5, 2.0, 1.5
#: Greatest log odds of the tree against a place.
AGAINST = 4.0
_TOKEN = re.compile(r"<!--.*?(?:-->|\Z)|<(/?)([a-zA-Z][^\s/>]*)((?:[^>\"']|\"[^\"]*\"|'[^']*')*)>|<[!?/][^>]*(?:>|\Z)|<[a-zA-Z][^>]*\Z", re.S)
_NAMES = re.compile(r"(?:^|\s)(?:class|id|role)\s*=\s*(?:\"([^\"]*)\"|'([^']*)'|([^\s\"'>]+))", re.I)
#: Fixed word lists of HTML.
_RAW = {"script", "style", "title", "textarea", "noscript", "template", "iframe", "xmp", "noembed", "noframes"}
_VOID = {"area", "base", "br", "col", "embed", "hr", "img", "input", "link", "meta", "source", "track", "wbr"}
_INLINE = {"a", "abbr", "acronym", "b", "bdi", "bdo", "big", "cite", "code", "data", "del", "dfn", "em", "font", "i", "ins", "kbd", "label", "mark", "q", "rp", "rt", "ruby", "s", "samp", "small", "span", "strike", "strong", "sub", "sup", "time", "tt", "u", "var", "picture", "nobr"}
_CLOSES_P = {"address", "article", "aside", "blockquote", "center", "details", "dialog", "dir", "div", "dl", "fieldset", "figcaption", "figure", "footer", "form", "h1", "h2", "h3", "h4", "h5", "h6", "header", "hgroup", "hr", "main", "menu", "nav", "ol", "p", "pre", "section", "summary", "table", "ul"}
_SAME = {"li": {"li"}, "dt": {"dt", "dd"}, "dd": {"dt", "dd"}, "tr": {"tr", "td", "th"}, "td": {"td", "th"}, "th": {"td", "th"}, "option": {"option"}}
_NOISE_TAGS = {"nav", "footer", "aside", "form", "button", "select", "dialog", "menu", "head", "object", "svg", "math", "canvas", "audio", "video", "fieldset"}
_NOISE_NAMES = {"ad", "ads", "adv", "advert", "adverts", "advertisement", "advertising", "banner", "breadcrumb", "breadcrumbs", "comment", "comments", "consent", "cookie", "cookies", "disclaimer", "footer", "gdpr", "header", "login", "masthead", "menu", "modal", "nav", "navbar", "navigation", "newsletter", "notice", "notices", "pagination", "popup", "promo", "promoted", "recommended", "related", "replies", "respond", "search", "share", "sharing", "sidebar", "signup", "skip", "social", "sponsor", "sponsored", "subscribe", "tags", "toolbar", "topbar", "widget", "contentinfo", "complementary", "alert"}
_MAIN_NAMES = {"article", "main", "post", "entry", "story"}


_WITHOUT = re.compile(r"(?<![a-z0-9_-])(?:has|no|with|without)[-_][a-z0-9_-]*")


def _kind(tag: str, names: set[str], inside: bool) -> int:
    """-2 noise by element, -1 noise by name, 1 main text, 0 neither."""
    if tag in _NOISE_TAGS or tag == "header" and not inside:
        return -2
    if tag in ("article", "main", "body", "html"):
        return 1 if tag in ("article", "main") else 0
    if names & _NOISE_NAMES and not (inside and names <= {"header", *_MAIN_NAMES}):
        return -1
    return 1 if names & _MAIN_NAMES else 0


def _hash(text: str) -> int:
    """Signed 64-bit hash."""
    value = xxhash.xxh64_intdigest(text.encode("utf-8", "surrogatepass"))
    return value - (1 << 64) if value >> 63 else value


@dataclass
class _Open:
    """An element that is not closed yet."""

    tag: str
    place: int
    path: tuple[int, ...]
    kind: int
    heading: bool
    children: list[int] = field(default_factory=list)


@dataclass
class Page:
    """Blocks (leaf place, kind, heading, text) in order, and the page's tree: per place its path, how often it occurs and its share of its parent's children."""

    blocks: list[tuple[int, int, bool, str]] = field(default_factory=list)
    paths: dict[int, tuple[int, ...]] = field(default_factory=dict)
    occurs: Counter = field(default_factory=Counter)
    share: Counter = field(default_factory=Counter)
    styles: set[tuple[int, int]] = field(default_factory=set)
    boxes: set[int] = field(default_factory=set)

    def close(self, e: _Open) -> None:
        if not e.children:
            return
        self.styles.add((e.place, _hash(",".join(map(str, e.children)))))
        for place, n in Counter(e.children).items():
            self.share[place] += n / len(e.children)


def parse(page: str) -> Page:
    """Blocks and tree of a page. Kinds of blocks: -2 and -1 noise by element and by name, 0, 1 main text by name, 2 by element.

    Main text by element inside a wrapper whose name says noise is main text where the page has none outside such wrappers.
    """
    out = Page()
    stack = [_Open("", _hash(""), (), 0, False)]
    out.paths[stack[0].place] = ()
    out.occurs[stack[0].place] = 1
    run: list[str] = []

    def flush():
        if run:
            text = " ".join("".join(run).split())
            run.clear()
            if text:
                e = stack[-1]
                leaf = _hash(f"{e.place}#")
                out.paths.setdefault(leaf, (*e.path, e.place))
                out.occurs[leaf] += 1
                e.children.append(leaf)
                out.blocks.append((leaf, e.kind, e.heading, text))

    def drop(k: int):
        for e in stack[k:]:
            if len(e.path) <= MAX_DEPTH:
                out.close(e)
        del stack[k:]

    at, size = 0, len(page)
    while at < size:
        m = _TOKEN.search(page, at)
        if m is None:
            run.append(entities.unescape(page[at:]))
            break
        if m.start() > at:
            run.append(entities.unescape(page[at : m.start()]))
        at = m.end()
        tag = m[2]
        if tag is None:
            continue
        tag = tag.lower()
        if tag in _INLINE:
            continue
        if tag == "br" or tag in ("img", "input", "wbr"):
            if tag != "wbr":
                run.append(" ")
            continue
        if m[1]:
            if tag in _VOID:
                continue
            flush()
            for k in range(len(stack) - 1, 0, -1):
                if stack[k].tag == tag:
                    drop(k)
                    break
            continue
        flush()
        if tag in _RAW:
            end = re.compile(rf"</{tag}(?=[\s/>])[^>]*(?:>|\Z)", re.I).search(page, at)
            at = end.end() if end else size
            continue
        if tag in _VOID:
            continue
        if tag in _CLOSES_P and stack[-1].tag == "p":
            drop(len(stack) - 1)
        same = _SAME.get(tag)
        if same:
            for k in range(len(stack) - 1, 0, -1):
                if stack[k].tag in same:
                    drop(k)
                    break
                if stack[k].tag in ("ul", "ol", "dl", "table", "tbody", "select"):
                    break
        if tag == "body":
            while len(stack) > 1 and stack[-1].tag != "html":
                drop(len(stack) - 1)
        names: set[str] = set()
        sign = tag
        if m[3].strip():
            words = " ".join(a or b or c for a, b, c in _NAMES.findall(m[3])).lower()
            names = set(re.split(r"[^a-z0-9]+", words)) - {""}
            if names:
                sign += "." + ".".join(sorted(x for x in names if not x.isdigit()))
            names = set(re.split(r"[^a-z0-9]+", _WITHOUT.sub(" ", words))) - {""}
        above = stack[-1]
        own = _kind(tag, names, above.kind > 0)
        if own == 1 and tag in ("article", "main"):
            own = 2
        if above.kind == -1 and own == 2:
            own = 3  # within a wrapper named as noise
        elif above.kind < 0 or own < 0:
            own = min(above.kind, own)
        else:
            own = max(above.kind, own)
        if len(above.path) >= MAX_DEPTH:  # counts as its ancestor
            stack.append(_Open(tag, above.place, above.path, own, above.heading, above.children))
            continue
        place, path = _hash(f"{above.place}/{sign}"), (*above.path, above.place)
        out.paths.setdefault(place, path)
        out.occurs[place] += 1
        out.boxes.add(above.place)
        above.children.append(place)
        stack.append(_Open(tag, place, path, own, above.heading or tag == "h1"))
    flush()
    drop(0)
    wrapped = -1 if any(k == 2 for _, k, _, _ in out.blocks) else 2
    out.blocks = [(p, wrapped if k == 3 else k, h, t) for p, k, h, t in out.blocks]
    return out


def priors(blocks: list[tuple[int, int, bool, str]]) -> list[float]:
    """What each block's elements say, in log odds. A main-like name on less text than the unnamed blocks hold says nothing of these."""
    named, plain = (sum(len(t) for _, k, _, t in blocks if k == kind) for kind in (1, 0))
    beside = BESIDE if any(k == 2 for _, k, _, _ in blocks) or named and named >= plain else PLAIN
    says = {-2: NEVER, -1: NAMED, 0: beside, 1: LIKE, 2: MAIN}
    return [says[k] + (HEADING if h and k >= 0 else 0.0) for _, k, h, _ in blocks]


_NODES = "array<struct<place:bigint,path:array<bigint>,leaf:boolean,box:boolean,occurs:int,share:double,chars:bigint>>"
_PAGE = f"url string, copy bigint, sig bigint, blocks array<struct<place:bigint,says:double,text:string>>, contents array<struct<place:bigint,key:bigint>>, styles array<struct<place:bigint,style:bigint>>, nodes {_NODES}"


def _row(page: str) -> dict:
    made = parse(page)
    says = priors(made.blocks)
    keys = [_hash(t) for _, _, _, t in made.blocks]
    leaves = {p for p, _, _, _ in made.blocks}
    used = leaves | {x for p in leaves for x in made.paths[p]}
    chars: Counter = Counter()
    for p, _, _, t in made.blocks:
        chars[p] += len(t)
    main = [k for k, s in zip(keys, says, strict=True) if s > 0]
    nodes = []
    for p in sorted(used):
        path = made.paths[p]
        nodes.append({"place": p, "path": path, "leaf": p in leaves, "box": p in made.boxes, "occurs": made.occurs[p], "share": made.share[p] / made.occurs[path[-1]] if path else 1.0, "chars": chars[p]})
    return {
        "copy": _hash(",".join(map(str, main or keys))),
        "sig": _hash(",".join(map(str, sorted(leaves)))),
        "blocks": [{"place": p, "says": s, "text": t} for (p, _, _, t), s in zip(made.blocks, says, strict=True)],
        "contents": [{"place": p, "key": k} for p, k in sorted({(p, k) for (p, _, _, _), k in zip(made.blocks, keys, strict=True)})],
        "styles": [{"place": p, "style": x} for p, x in sorted(made.styles) if p in used],
        "nodes": nodes,
    }


def parsed_pages(pages: DataFrame) -> DataFrame:
    """page_id, url, host and what _row() finds of every page."""
    kind = pages.schema["page_id"].dataType.simpleString()
    node = pa.struct([("place", pa.int64()), ("path", pa.list_(pa.int64())), ("leaf", pa.bool_()), ("box", pa.bool_()), ("occurs", pa.int32()), ("share", pa.float64()), ("chars", pa.int64())])
    kinds = {
        "copy": pa.int64(), "sig": pa.int64(), "blocks": pa.list_(pa.struct([("place", pa.int64()), ("says", pa.float64()), ("text", pa.string())])),
        "contents": pa.list_(pa.struct([("place", pa.int64()), ("key", pa.int64())])), "styles": pa.list_(pa.struct([("place", pa.int64()), ("style", pa.int64())])), "nodes": pa.list_(node),
    }

    def run(batches):
        for batch in (part for whole in batches for part in slices(whole, 2)):
            rows = [_row(page or "") for page in batch.column(2).to_pylist()]
            yield pa.RecordBatch.from_arrays([batch.column(0), batch.column(1), *(pa.array([r[k] for r in rows], t) for k, t in kinds.items())], names=["page_id", "url", *kinds])

    made = pages.select("page_id", F.col("url").cast("string").alias("url"), F.col("html").cast("string").alias("html")).mapInArrow(run, f"page_id {kind}, {_PAGE}")
    return made.withColumn("host", F.coalesce(F.lower(F.regexp_extract("url", r"^(?:[A-Za-z][A-Za-z0-9+.-]*:)?//([^/?#]*)", 1)), F.lit("")))


def places(parsed: DataFrame) -> DataFrame:
    """The style trees: host, place, path, leaf, box, pages, occurs, share (sum over pages), chars, kinds (presentations) and own importance."""
    tree = ["contents", "styles", "nodes"]
    once = parsed.groupBy("host", "copy").agg(F.min(F.struct(F.xxhash64(*tree).alias("h"), *tree)).alias("page"))
    once = materialise(once.select("host", *[F.col(f"page.{c}").alias(c) for c in tree]), "distinct-pages")

    def counted(column: str, what: str) -> DataFrame:
        each = once.select("host", F.explode(column).alias("x")).select("host", "x.*").groupBy("host", "place", what).agg(F.count("*").alias("n"))
        return each.groupBy("host", "place").agg(F.count("*").alias(f"{column}_kinds"), F.sum(F.log("n")).alias(f"{column}_logs"), F.sum("n").alias(f"{column}_n"), F.sum(F.col("n") * F.log("n")).alias(f"{column}_weighted"))

    nodes = once.select("host", F.explode("nodes").alias("x")).select("host", "x.*").groupBy("host", "place").agg(
        F.first("path").alias("path"), F.first("leaf").alias("leaf"), F.max("box").alias("box"), F.count("*").alias("pages"), F.sum("occurs").alias("occurs"), F.sum("share").alias("share"), F.sum("chars").alias("chars")
    )
    both = nodes.join(counted("contents", "key"), ["host", "place"], "left").join(counted("styles", "style"), ["host", "place"], "left")
    unit = F.log(F.greatest(F.col("pages"), F.lit(2)).cast("double"))
    recurs = F.greatest(F.lit(0.0), 1 - F.col("contents_logs") / F.col("contents_kinds") / unit)
    spread = F.least(F.lit(1.0), (F.log("styles_n") - F.col("styles_weighted") / F.col("styles_n")) / unit)
    own = F.when(F.col("pages") == 1, 1.0).when(F.col("leaf"), recurs).otherwise(F.coalesce(spread, F.lit(0.0)))
    made = both.select("host", "place", "path", "leaf", "box", "pages", "occurs", "share", "chars", F.coalesce("styles_kinds", F.lit(1)).alias("kinds"), own.alias("own"))
    made = materialise(made, "style-trees")
    discard(once)
    return made


def importance(tree: DataFrame, decay: float = DECAY) -> DataFrame:
    """host, place, composite importance and weight (text less what recurs, times composite importance) of every place.

    A node passes on to each ancestor its own part times the shares on the way, so the recursion from the leaves up is one sum over
    (node, ancestor) pairs, at most MAX_DEPTH + 1 for a node.
    """
    up = tree.select("host", F.col("place").alias("parent"), F.col("pages").alias("up_pages"), F.pow(F.lit(decay), "kinds").alias("up_rest"))
    steps = tree.withColumn("parent", F.try_element_at("path", F.lit(-1))).join(up, ["host", "parent"], "left").select(
        "host", "place", "path",
        F.when(F.col("leaf"), F.col("own")).otherwise((1 - F.pow(F.lit(decay), "kinds")) * F.col("own")).alias("part"),
        F.when(F.col("leaf"), F.col("chars") * F.col("own")).otherwise(0.0).alias("mass"),
        (F.col("up_rest") * F.col("share") / F.col("up_pages")).alias("step"),
    )
    steps = materialise(steps, "tree-steps")
    chain = steps.select("host", F.col("place").alias("node"), "part", "mass", F.posexplode(F.concat("path", F.array("place"))).alias("i", "place"))
    chain = chain.join(steps.select("host", "place", "step"), ["host", "place"]).groupBy("host", "node").agg(F.first("part").alias("part"), F.first("mass").alias("mass"), F.array_sort(F.collect_list(F.struct("i", "place", "step"))).alias("chain"))
    passed = chain.select("host", "part", "mass", F.expr("explode(transform(chain, (c, k) -> struct(c.place as place, aggregate(slice(chain, k + 2, size(chain)), 1D, (a, s) -> a * s.step) as passed)))").alias("x"))
    sums = passed.groupBy("host", "x.place").agg(F.sum(F.col("part") * F.col("x.passed")).alias("importance"), F.sum("mass").alias("mass"))
    return sums.select("host", "place", "importance", (F.col("mass") * F.col("importance")).alias("weight"))


def odds(tree: DataFrame, weighed: DataFrame, prior_pages: int = PRIOR_PAGES) -> DataFrame:
    """host, place and the tree's log odds that the place is main text, of every content place."""
    up = weighed.select("host", F.col("place").alias("parent"), F.col("weight").alias("up_weight"))
    branch = tree.withColumn("parent", F.try_element_at("path", F.lit(-1))).join(weighed, ["host", "place"]).join(up, ["host", "parent"], "left")
    part = F.when(F.col("parent").isNull(), 1.0).otherwise(F.coalesce(F.try_divide("weight", "up_weight"), F.lit(0.0)))
    branch = branch.select("host", "place", "path", "leaf", "pages", "own", "parent", part.alias("part"), ((part > 0.5) & F.col("box") & (F.col("occurs") <= 1.5 * F.col("pages"))).alias("main"))
    branch = materialise(branch, "branches")
    goes_on = branch.where("main and parent is not null").select("host", F.col("parent").alias("place"), F.lit(True).alias("on"))
    nodes = branch.select("host", "place", "part", "main").join(goes_on, ["host", "place"], "left").select("host", "place", "part", "main", F.coalesce("on", F.lit(False)).alias("on"))
    chain = branch.where("leaf").select("host", F.col("place").alias("leaf_place"), "pages", "own", F.posexplode(F.concat("path", F.array("place"))).alias("i", "place"))
    chain = chain.join(nodes, ["host", "place"]).groupBy("host", "leaf_place").agg(F.first("pages").alias("pages"), F.first("own").alias("own"), F.array_sort(F.collect_list(F.struct("i", "part", "main", "on"))).alias("chain"))
    # last node on the main path, counted from 0; the root is on it
    last = F.expr("coalesce(array_position(transform(slice(chain, 2, size(chain)), c -> c.main), false) - 1, 0)")
    chain = chain.withColumn("last", last)
    inside = F.when(F.col("own") >= 0.5, 2 * F.col("own") - 1).otherwise(AGAINST * (2 * F.col("own") - 1))
    share = F.expr("chain[int(last) + 1].part")
    outside = F.greatest(F.lit(-AGAINST), F.least(F.lit(0.0), F.log(F.greatest(share, F.lit(1e-9)) / F.greatest(1 - share, F.lit(1e-9))) + F.least(F.lit(0.0), inside)))
    value = F.when(F.expr("chain[int(last)].on"), outside).otherwise(inside)
    return chain.select("host", F.col("leaf_place").alias("place"), (value * F.col("pages") / (F.col("pages") + prior_pages)).alias("odds"))


def extract(pages: DataFrame, prior_pages: int = PRIOR_PAGES) -> DataFrame:
    """page_id, url, text, n_chars, n_blocks, n_removed and n_decided_by_tree (blocks of which the tree says more than their elements) of every page."""
    parsed = materialise(parsed_pages(pages), "page-blocks")
    tree = places(parsed)
    judged = odds(tree, materialise(importance(tree), "weights"), prior_pages)
    forms = parsed.select("host", "sig", F.array_distinct(F.col("blocks.place")).alias("places")).groupBy("host", "sig").agg(F.first("places").alias("places"))
    looked = forms.select("host", "sig", F.explode("places").alias("place")).join(judged, ["host", "place"]).groupBy("host", "sig").agg(F.map_from_entries(F.collect_list(F.struct("place", "odds"))).alias("odds"))
    looked = materialise(looked, "odds-by-form")
    few = (looked.agg(F.sum(F.size("odds"))).first()[0] or 0) <= BROADCAST_ROWS
    joined = parsed.select("page_id", "url", "host", "sig", "blocks").join(F.broadcast(looked) if few else looked, ["host", "sig"], "left")
    # says and tree's odds of every block
    scored = joined.withColumn("b", F.expr("transform(blocks, b -> struct(b.text as text, b.says as says, coalesce(odds[b.place], 0D) as odds))"))
    length = "aggregate({}, 0L, (n, b) -> n + length(b.text))"
    kept, lost, named = "filter(b, x -> x.says + x.odds > 0)", f"filter(b, x -> x.says >= {LIKE} and x.says + x.odds <= 0)", f"filter(b, x -> x.says = {NAMED} and x.odds >= 0)"
    whole = f"case when {length.format(lost)} > {length.format(kept)} then filter(b, x -> x.says >= {LIKE} or x.says + x.odds > 0) when size({kept}) > 0 then {kept} else {named} end"
    text = scored.withColumn("kept", F.expr(whole)).withColumn("text", F.expr("array_join(transform(kept, x -> x.text), '\n')"))
    return text.select("page_id", "url", "text", F.length("text").cast("long").alias("n_chars"), F.size("b").cast("long").alias("n_blocks"), (F.size("b") - F.size("kept")).cast("long").alias("n_removed"), F.expr("cast(size(filter(b, x -> abs(x.odds) > abs(x.says))) as long)").alias("n_decided_by_tree"))
