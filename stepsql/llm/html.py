"""Main text of web pages by site style trees.

Pages of one host are merged into a style tree: a node is the path of elements (tag and class) from the
root. Its presentation importance is the entropy of the child sequences seen there, its content importance the
entropy of the texts seen in its whole branch, each over the logarithm of the number of pages with that node, so 0 means
that all pages agree and 1 that all differ. A branch that is low in both is boilerplate of
the site and is cut from every page, inside and outside article elements.

Entropy alone errs where a menu or an advert differs on every page. Elements that name a role (nav, footer, aside, form; class or id words such
as ad, menu, comments) therefore start from a small prior instead of 1, which the branch's share of its parent's words outside links
raises: importance = content * (prior + weight * share). Words and shares are sums over the pages of the host, drawn towards those of the
same path on all hosts, so that a host of few pages borrows what others show. A branch that holds much of its pages' text
stays whatever its name says; what is under the threshold is cut. Scripts, styles, form controls and hidden elements hold no text.

An article that would lose more than half of its text for being common is a copy as a whole and stays. A page read without its site's tree has
its markup alone: its articles, or all that names no role. Pages are read in one pass without recursion or backtracking, in time linear in
their length.
"""

from __future__ import annotations

import functools
import html as entities
import re
from collections import Counter
from collections.abc import Iterator
from dataclasses import dataclass
from hashlib import blake2b

import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from .common import map_batches, pick, ship, written

# Element names of HTML by what they mean here.
VOID = frozenset("area base br col embed hr img input link meta param source track wbr".split())
RAW = frozenset("script style textarea title xmp noembed noframes iframe".split())
BLOCK = frozenset(
    "address article aside blockquote body caption center dd details dialog dir div dl dt fieldset figcaption figure footer form "
    "h1 h2 h3 h4 h5 h6 head header hgroup hr html legend li main menu nav ol optgroup option p pre section summary table tbody "
    "td tfoot th thead tr ul".split()
)
CLOSES_P = BLOCK - frozenset("body caption dd dt head html legend li optgroup option summary tbody td tfoot th thead tr".split())
TEXTLESS = frozenset(
    "head script style noscript template iframe button select option textarea label input object embed svg canvas audio video map datalist fieldset".split()
)
ROLES = frozenset("nav footer aside form menu dialog".split())
ROLE_WORDS = frozenset(
    "ad ads adv advert adverts advertisement advertising adsense banner sponsor sponsored promo promotion teaser cookie cookies consent gdpr notice notices "
    "alert popup modal overlay sidebar side aside menu nav navbar navigation breadcrumb breadcrumbs footer foot "
    "related recommended share sharing social newsletter subscribe subscription signup login widget toolbar pagination pager "
    "skip copyright masthead".split()
)
COMMENT_WORDS = frozenset("comment comments reply replies respond disqus".split())
OUTER_WORDS = frozenset("header head top topbar".split())
ROLE_NAMES = frozenset("navigation banner contentinfo complementary search form alert dialog menu menubar".split())
ARTICLE_WORDS = frozenset("article articlebody".split())
ARTICLE_ROLE_WORDS = frozenset("ad ads advert advertisement sponsored promo teaser related recommended".split())
#: Branches that are judged as such; other elements go with the branch that they stand in, unless they hold text themselves.
CONTAINERS = frozenset("div section aside nav header footer form ul ol dl table td figure details menu dialog blockquote".split())

_ATTRIBUTE = re.compile(r"(?:^|[\s\"'])(class|id|role|itemprop|hidden|aria-hidden)(?:\s*=\s*(?:\"([^\"]*)\"|'([^']*)'|([^\s\"'>]+)))?(?=[\s\"'/]|$)", re.I)
_WORDS = re.compile(r"[a-z]+")
_NAME = re.compile(r"<(/?)([a-zA-Z][^\s/>]*)")
_PLAIN = re.compile(r"[^'\">]*")
_RAW_END = {tag: re.compile(rf"</{tag}[\s/>]", re.I) for tag in RAW}


@dataclass(frozen=True)
class Config:
    least: float = 0.25  # branches under this importance are cut
    support: int = 3  # pages a branch needs on its host before its entropies count
    prior: float = 0.1  # importance of a branch that names a role and holds none of its parent's words
    weight: float = 0.9  # what it gains if it holds all of them
    comment_weight: float = 0.1  # the same for reader comments, which may be longer than the article
    pages: float = 10.0  # pages of all hosts that a host's words are averaged with
    broadcast_rows: int = 200_000  # cut branches up to which they are broadcast; more are joined to the pages' own branches by a shuffle


class Element:
    __slots__ = ("tag", "key", "parent", "textless", "role", "named", "article", "common", "dropped", "children", "own", "mark", "words")

    def __init__(self, tag: str, key: int, parent: int, textless: bool, role: int, named: bool, article: bool, common: bool, dropped: bool):
        self.tag, self.key, self.parent, self.textless, self.role, self.named, self.article = tag, key, parent, textless, role, named, article
        self.common, self.dropped = common, dropped  # by the site's tree, own or from above
        self.children: list[str] = []
        self.own = False  # holds text itself
        self.mark = self.words = 0  # digest and words outside links of the branch


def _attributes(text: str) -> dict[str, str]:
    return {m[1].lower(): (m[2] or m[3] or m[4] or "").lower() for m in _ATTRIBUTE.finditer(text)} if text else {}


def _is_article(tag: str, own: dict[str, str]) -> bool:
    return tag in ("article", "main") or bool(own) and (own.get("role") in ("main", "article") or bool(ARTICLE_WORDS & set(_WORDS.findall(f"{own.get('class', '')} {own.get('id', '')} {own.get('itemprop', '')}"))))


def _role(tag: str, own: dict[str, str], in_article: bool) -> int:
    """What an element's markup calls it: 0 nothing, 1 a part around the text, 2 reader comments."""
    if tag in ("html", "body", "main"):
        return 0
    if not own:
        return int(tag in ROLES or not in_article and tag == "header")
    words = set(_WORDS.findall(own.get("class", "") + " " + own.get("id", "")))
    if words & COMMENT_WORDS:
        return 2
    if tag == "article":
        return int(bool(words & ARTICLE_ROLE_WORDS))
    named = tag in ROLES or own.get("role", "") in ROLE_NAMES or words & ROLE_WORDS
    return int(bool(named or not in_article and (tag == "header" or words & OUTER_WORDS)))


def _tag_end(page: str, at: int) -> int:
    """Place of the > that ends the tag whose attributes begin at `at`; -1 if there is none. A quote without its like is a plain character."""
    n = len(page)
    while at < n:
        m = _PLAIN.match(page, at)
        at = m.end()
        if at >= n:
            return -1
        if page[at] == ">":
            return at
        end = page.find(page[at], at + 1)
        if end < 0:
            return page.find(">", at + 1)
        at = end + 1
    return -1


def _tokens(page: str) -> Iterator[tuple[str, str, str]]:
    """('text', text, ''), ('open', tag, attributes) and ('close', tag, '') in page order; the inside of raw elements is an attribute-like third part
    of ('raw', tag, inside). Each character is looked at a bounded number of times."""
    at, n = 0, len(page)
    while at < n:
        start = page.find("<", at)
        if start < 0:
            yield "text", page[at:], ""
            return
        m = _NAME.match(page, start)
        if m is None:
            if page.startswith("<!--", start):
                if start > at:
                    yield "text", page[at:start], ""
                end = page.find("-->", start + 4)
                at = n if end < 0 else end + 3
                continue
            if page.startswith(("<!", "<?"), start):
                end = page.find(">", start)
                if end < 0:
                    yield "text", page[at:], ""
                    return
                if start > at:
                    yield "text", page[at:start], ""
                at = end + 1
                continue
            yield "text", page[at : start + 1], ""
            at = start + 1
            continue
        end = _tag_end(page, m.end())
        if end < 0:  # no tag ends from here on
            yield "text", page[at:], ""
            return
        if start > at:
            yield "text", page[at:start], ""
        tag = m[2].lower()
        at = end + 1
        if m[1]:
            yield "close", tag, ""
            continue
        yield "open", tag, page[m.end() : end]
        if tag in RAW:
            close = _RAW_END[tag].search(page, at)
            inside = page[at : close.start() if close else n]
            at += len(inside)
            yield "raw", tag, inside


def hash_of(text: str) -> int:
    return int.from_bytes(blake2b(text.encode("utf-8", "surrogatepass"), digest_size=8).digest(), "little", signed=True)


@functools.lru_cache(100_000)
def _key(above: int, name: str) -> int:
    return hash_of(f"{above}/{name}") & ~1


@functools.lru_cache(100_000)
def _shape(run: tuple[str, ...]) -> int:
    return hash_of(",".join(run))


def parse(page: str, cut: frozenset[int] | set[int] = frozenset(), marks: bool = False) -> Iterator[tuple[str, Element, str]]:
    """('text', element, whole text of a block), in page order, and ('end', element, '') as each element ends.

    A block goes to the element that was open where its first text stood. Unclosed and stray tags are mended as far as blocks need it. An element's key
    is the digest of its path, even; cut holds keys of common branches, and of branches to drop for their role as key + 1. Digests of texts and of what
    raw elements hold are made if marks is set."""
    stack = [Element("", 0, 0, False, 0, False, False, False, False)]
    blocks: list[int] = []  # places of block elements in the stack
    open_: Counter[str] = Counter()
    held: list[str] = []
    holder = stack[0]

    def flush() -> Iterator[tuple[str, Element, str]]:
        nonlocal held
        if held:
            text = " ".join(entities.unescape("".join(held)).split())
            held = []
            if text:
                holder.own = True
                if marks:
                    holder.mark = hash((holder.mark, hash_of(text)))
                yield "text", holder, text

    def hold(text: str) -> None:
        nonlocal holder
        if not held and not text.isspace():
            holder = stack[-1]
        if held or not text.isspace():
            held.append(text)
            if not open_["a"]:
                stack[-1].words += len(text.split())

    def close(depth: int) -> Iterator[tuple[str, Element, str]]:
        while len(stack) > depth:
            e = stack.pop()
            open_[e.tag] -= 1
            if blocks and blocks[-1] == len(stack):
                blocks.pop()
            yield "end", e, ""
            if e.mark:
                stack[-1].mark = hash((stack[-1].mark, e.mark))
            if not e.textless:
                stack[-1].words += e.words

    for kind, tag, rest in _tokens(page):
        if kind == "text":
            # text of different standing never shares a block
            if held and (holder.textless, holder.role, holder.article, holder.dropped) != (stack[-1].textless, stack[-1].role, stack[-1].article, stack[-1].dropped):
                yield from flush()
            hold(tag)
            continue
        if kind == "raw":
            if marks:
                stack[-1].children.append(format(hash_of(rest), "x"))
            continue
        if kind == "close":
            if tag in BLOCK or tag == "br":
                yield from flush()
            if open_[tag] > 0:
                k = len(stack) - 1
                while stack[k].tag != tag:
                    k -= 1
                yield from close(k)
            continue
        if tag in BLOCK:
            yield from flush()
        if tag == "br":
            hold(" ")
        if tag in CLOSES_P or tag in ("li", "dt", "dd", "tr", "td", "th", "option"):
            # an open p, or an open sibling of the same kind, ends here; containers stop the search
            ends = {"p"} if tag in CLOSES_P else {"dt", "dd", "p"} if tag in ("dt", "dd") else {"td", "th", "p"} if tag in ("td", "th") else {tag, "p", "td", "th"} if tag == "tr" else {tag, "p"}
            cut_at = None
            for k in reversed(blocks):
                if stack[k].tag not in ends:
                    break
                cut_at = k
            if cut_at is not None:
                yield from close(cut_at)
        above = stack[-1]
        own = _attributes(rest)
        above.children.append(tag)
        if tag in VOID:
            continue
        textless = above.textless or tag in TEXTLESS or tag not in ("html", "body") and ("hidden" in own or own.get("aria-hidden") == "true")
        named = _role(tag, own, above.article)
        role = above.role or named
        key = _key(above.key, tag + ("." + own["class"] if own.get("class") else ""))
        article = above.article or not textless and not role and tag not in ("html", "body") and _is_article(tag, own)
        e = Element(tag, key, above.key, textless, role, named > 0, article, above.common or key in cut, above.dropped or key + 1 in cut)
        if tag in BLOCK:
            blocks.append(len(stack))
        stack.append(e)
        open_[tag] += 1
    yield from flush()
    yield from close(1)


def style_nodes(page: str | None) -> list[tuple]:
    """(path, role, judged, shape, mark, words, around) of the style nodes of one page: digests of the child sequences and of the texts of the
    branch (null without text), words outside links in it and in its parent's branch."""
    found: dict[int, list] = {}
    words: Counter[int] = Counter()
    for event, e, _ in parse(page or "", marks=True):
        if event != "end":
            continue
        run = tuple(c for i, c in enumerate(e.children) if i == 0 or c != e.children[i - 1])
        node = found.setdefault(e.key, [e.parent, (2 if e.role == 2 else 1) if e.named else 0, False, 0, 0])
        node[2] = node[2] or e.own or e.tag in CONTAINERS
        node[3] = hash((node[3], _shape(run)))
        if e.mark and not e.textless:
            node[4] = hash((node[4], e.mark))
        if not e.textless:
            words[e.key] += e.words
    # words of the root are those of its children
    words[0] = sum(words[k] for k, node in found.items() if node[0] == 0)
    return [(key, role, judged, shape, mark or None, words[key], words[parent]) for key, (parent, role, judged, shape, mark) in found.items()]


def main_text(page: str | None, cut: frozenset[int] | set[int] | None = None) -> str:
    """Main text of one page, in page order, given the style-tree branches that its host cuts (none known: None). Where the common ones would leave
    nothing, the page is a copy of others as a whole, and they stay; likewise in an article that they would take more than half of."""
    blocks = [(text, e) for event, e, text in parse(page or "", cut or frozenset()) if event == "text" and not e.textless]
    if cut is None:
        plain = [(text, e) for text, e in blocks if not e.role]
        has_article = any(e.article for _, e in plain)
        return "\n".join(text for text, e in plain if e.article or not has_article)
    found = [(text, e) for text, e in blocks if not e.dropped]
    whole = sum(len(text) for text, e in found if e.article)
    copied = 2 * sum(len(text) for text, e in found if e.article and e.common) > whole
    kept = [text for text, e in found if not e.common or e.article and copied]
    return "\n".join(kept or [text for text, _ in found])


def importance(pages: DataFrame, config: Config = Config()) -> DataFrame:
    """host, path, role, judged, pages, presentation, content, share, importance of every style-tree node (content: null if never seen with text).

    Counts of equal values are added up in each task before they are dealt out, so a large host costs no more a task than a small one."""
    ship(pages.sparkSession)
    names = ("path", "role", "judged", "shape", "mark", "words", "around")

    def run(b: pa.RecordBatch) -> dict:
        rows = [(host, *node) for host, page in zip(b.column(0).to_pylist(), b.column(1).to_pylist()) for node in style_nodes(page)]
        return dict(zip(("host", *names), zip(*rows))) if rows else {name: [] for name in ("host", *names)}

    seen = map_batches(pages.select("host", "html"), run, "host string, path bigint, role int, judged boolean, shape bigint, mark bigint, words bigint, around bigint", rows=128)
    kinds = F.inline(F.array(F.struct(F.lit(0).alias("kind"), F.col("shape").alias("value")), F.struct(F.lit(1).alias("kind"), F.col("mark").alias("value"))))
    counts = seen.select("host", "path", "role", "judged", "words", "around", kinds).where("value is not null").groupBy("host", "path", "kind", "value").agg(
        F.count("*").alias("c"), F.max("role").alias("role"), F.max("judged").alias("judged"), F.sum("words").alias("words"), F.sum("around").alias("around")
    )
    parts = counts.groupBy("host", "path", "kind").agg(
        F.sum("c").alias("m"), F.sum(F.col("c") * F.log("c")).alias("s"), F.max("role").alias("role"), F.max("judged").alias("judged"), F.sum("words").alias("words"), F.sum("around").alias("around")
    )
    entropy = F.when(F.col("m") > 1, F.greatest(F.lit(0.0), 1 - F.col("s") / (F.col("m") * F.log("m")))).otherwise(F.lit(1.0))
    style = lambda c: F.max(F.when(F.col("kind") == 0, c))
    # three uses; pages are read once for all of them
    nodes = parts.groupBy("host", "path").agg(
        F.max("role").alias("role"), F.max("judged").alias("judged"), F.max("m").alias("pages"), style(entropy).alias("presentation"),
        F.max(F.when(F.col("kind") == 1, entropy)).alias("content"), style(F.col("words")).alias("words"), style(F.col("around")).alias("around"),
    )
    nodes = written(nodes)
    # means of a path over all hosts, for those that name a role; a path that many hosts have is dealt out by host
    salts, salt = 32, F.pmod(F.xxhash64("host"), F.lit(32))
    named = nodes.where("role > 0")
    everywhere = named.groupBy("path").agg((F.sum("words") / F.sum("pages")).alias("mean_words"), (F.sum("around") / F.sum("pages")).alias("mean_around"))
    salted = everywhere.withColumn("salt", F.explode(F.sequence(F.lit(0), F.lit(salts - 1))))
    own = named.withColumn("salt", salt).join(salted, ["path", "salt"])
    around = F.col("around") + config.pages * F.col("mean_around")
    share = F.when(around > 0, (F.col("words") + config.pages * F.col("mean_words")) / around).otherwise(F.lit(0.0))
    known = F.when(F.col("pages") >= config.support, F.coalesce("content", F.lit(1.0))).otherwise(F.lit(1.0))
    gain = F.when(F.col("role") == 2, F.lit(config.comment_weight)).otherwise(F.lit(config.weight))
    fields = ("host", "path", "role", "judged", "pages", "presentation", "content", "share")
    weighed = own.withColumn("share", share).select(*fields, (known * (config.prior + gain * F.col("share"))).alias("importance"))
    plain = nodes.where("role = 0").withColumn("share", F.lit(1.0)).select(*fields, F.greatest(F.coalesce("content", F.lit(1.0)), "presentation").alias("importance"))
    return weighed.unionByName(plain)


def _branches(b: pa.RecordBatch) -> dict:
    out: dict[str, list] = {"host": [], "page": [], "path": []}
    for host, page, text in zip(*(c.to_pylist() for c in b.columns)):
        for path in {e.key for event, e, _ in parse(text or "") if event == "end"}:
            for name, v in zip(out, (host, page, path)):
                out[name].append(v)
    return out


def extract(pages: DataFrame, config: Config = Config()) -> DataFrame:
    """page_id, url, text, n_chars for every row of pages.

    Text is empty for a null or empty page and for one without main text; a page without a host in its url belongs to the
    host ''. Repeated rows give repeated results (and count as pages of their host). Whole pages count, however
    long. Other columns are ignored.
    """
    rows = pick(pages, "page_id", "url", "html").select(
        "page_id", "url", "html", F.lower(F.regexp_extract(F.coalesce("url", F.lit("")), r"^[A-Za-z][A-Za-z0-9+.-]*://([^/?#]*)", 1)).alias("host")
    )
    nodes = importance(rows, config)
    # branches without a role need pages enough to tell; keys of dropped roles are odd
    common = (F.col("role") == 0) & F.col("judged") & (F.col("pages") >= config.support)
    low = written(nodes.where((F.col("importance") < config.least) & ((F.col("role") > 0) | common)).select("host", (F.col("path") + (F.col("role") > 0).cast("bigint")).alias("path")))
    sets: dict[str, set[int]] = {}
    if low.count() <= config.broadcast_rows:
        for r in low.collect():
            sets.setdefault(r.host, set()).add(r.path)
        joined = rows.select("page_id", "url", "html", "host", F.lit(None).cast("array<bigint>").alias("cut"))
    else:
        # a page gets those of its own branches that its host cuts, however many these are; pages that are alike have them in common
        rows = rows.withColumn("page", F.coalesce(F.md5("html"), F.lit("")))
        own = map_batches(rows.select("host", "page", "html"), _branches, "host string, page string, path bigint", rows=128)
        cuts = own.join(low.withColumnRenamed("path", "key").withColumn("path", F.col("key").bitwiseAND(-2)), ["host", "path"]).groupBy("host", "page").agg(F.collect_set("key").alias("cut"))
        joined = rows.join(cuts, ["host", "page"], "left").select("page_id", "url", "html", "host", "cut")
    held = rows.sparkSession.sparkContext.broadcast(sets)

    def run(b: pa.RecordBatch) -> dict:
        texts = [main_text(p, frozenset(c) if c else held.value.get(h, frozenset())) for p, h, c in zip(*(b.column(k).to_pylist() for k in (2, 3, 4)))]
        return {"page_id": b.column(0), "url": b.column(1), "text": texts, "n_chars": [len(t) for t in texts]}

    return map_batches(joined.withColumn("page_id", F.col("page_id").cast("bigint")), run, "page_id bigint, url string, text string, n_chars bigint", rows=128)
