"""Main text of web pages, with site templates found by recurring subtrees.

Method. A page is parsed into elements. Every block element's subtree is hashed (tag, class
and id, own text, children). Per host, Spark counts on how many differing pages a subtree
occurs; one that recurs on ``MIN_PAGES`` or more belongs to the site's template and is deleted.
Pages count as differing by their main content, so that many copies of one article do not
make the article a template. Inside the main element (article or main) only containers can
be template, only those that hold less than half of its text, and only if they recur on
``INSIDE_SHARE`` of the host's differing pages: what some articles of a large site have in
common is content and stays.

What a template of too few pages leaves behind is then removed by the elements' own
declaration (``declared=False`` leaves this out): navigation, headers, footers, sidebars, forms,
scripts, styles and the like by tag or role, and notices, adverts, comments and so on by class and
id: by whole names everywhere, by words of compound names outside the main element and, for
containers and unmistakable words, inside it.

The text: the article (the longest, if there are several; else main, else what is left of
the body), character references decoded, white space inside a block as one space, trimmed,
blocks in page order joined by a line feed; empty blocks leave nothing.

Defined results: null html = empty page = empty text; a url without a host belongs to the
empty host; repeated rows are separate rows, but copies on a host count once for the
template; an empty table gives an empty result.
"""

from __future__ import annotations

import html as entities
import re
from collections.abc import Collection
from dataclasses import dataclass, field

import pyarrow as pa
import xxhash
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from . import common

MIN_PAGES = 5
INSIDE_SHARE = 0.2
#: Recurring subtrees of one host that are joined to its pages as one list; of other hosts each page has its own.
HOST_LIST = 10_000

#: HTML's elements by kind.
_VOID = frozenset("area base br col embed hr img input link meta param source track wbr".split())
_RAW = frozenset("script style xmp iframe noembed noframes".split())
_RCDATA = frozenset("textarea title".split())
_BLOCK = frozenset(
    "address article aside blockquote body center dd details dialog dir div dl dt fieldset figcaption figure footer form h1 h2 h3 h4 h5 h6"
    " header hgroup hr html legend li main menu nav ol optgroup option p pre search section summary table tbody td tfoot th thead tr ul caption".split()
)
_CONTAINER = frozenset("div section aside nav form header footer ul ol table dl details dialog figure menu".split())
#: Start tags that end an open element: what they end, and the elements the search stops at.
_ENDS = {"li": ({"li"}, {"ul", "ol", "menu"}), "dt": ({"dt", "dd"}, {"dl"}), "dd": ({"dt", "dd"}, {"dl"}), "tr": ({"tr"}, {"table"}), "td": ({"td", "th"}, {"tr", "table"}), "th": ({"td", "th"}, {"tr", "table"}), "option": ({"option"}, {"select"})}
_ENDS_P = _BLOCK - {"body", "html", "td", "th", "tr", "tbody", "thead", "tfoot", "caption", "option", "optgroup", "legend"}
_NOT_TEXT = frozenset(
    "head script style noscript template nav footer aside form iframe object embed applet svg math canvas audio video button select input textarea dialog menu xmp noembed noframes title".split()
)
_NOT_TEXT_ROLE = frozenset("navigation banner contentinfo complementary search dialog alertdialog alert menu menubar toolbar form".split())
_NOT_TEXT_WORD = frozenset(
    "ad ads advert adverts advertisement advertising sponsor sponsored promo promotion banner cookie cookies consent gdpr notice notices"
    " nav navbar navigation menu menus breadcrumb breadcrumbs sidebar sidebars footer masthead popup modal overlay newsletter subscribe signup"
    " share sharing social comment comments disqus reply replies related recommended teaser widget pagination pager toolbar".split()
)

#: Those of them that also tell inside compound names of containers in an article.
_PLAIN_WORD = frozenset(
    "advert adverts advertisement advertising sponsored cookie cookies consent gdpr navbar breadcrumb breadcrumbs sidebar sidebars masthead popup newsletter"
    " comment comments disqus pagination pager toolbar".split()
)

_TOKEN = re.compile(r"<!--.*?(?:-->|\Z)|<[!?][^>]*>?|<(/?)([A-Za-z][^\s/>]*)((?:[^>\"']|\"[^\"]*(?:\"|\Z)|'[^']*(?:'|\Z))*)>?", re.S)
_ATTRIBUTE = re.compile(r"(class|id|role|hidden|aria-hidden)(?:\s*=\s*(?:\"([^\"]*)\"|'([^']*)'|([^\s\"'>]+)))?(?=[\s/]|$)", re.I)
_NAME_WORD = re.compile(r"[a-z]+")


@dataclass(eq=False, slots=True)
class Element:
    tag: str
    role: str = ""
    names: str = ""
    children: list = field(default_factory=list)
    digest: int = 0
    weight: int = 0  # characters of text


def parse(text: str) -> Element:
    root = Element("#root")
    stack = [root]

    def close(tags, stop):
        for i in range(len(stack) - 1, 0, -1):
            if stack[i].tag in tags:
                del stack[i:]
                return
            if stack[i].tag in stop:
                return

    at = 0
    while at < len(text):
        m = _TOKEN.search(text, at)
        if not m:
            break
        if m.start() > at:
            stack[-1].children.append(text[at : m.start()])
        at = m.end()
        if m[2] is None:
            continue
        tag = m[2].lower()
        if m[1]:
            if tag == "p" and not any(e.tag == "p" for e in stack):
                stack[-1].children.append(Element("p"))
            for i in range(len(stack) - 1, 0, -1):
                if stack[i].tag == tag:
                    del stack[i:]
                    break
                if stack[i].tag in ("table", "article", "main", "body") and tag not in _BLOCK:
                    break
            continue
        if tag in _ENDS:
            close(*_ENDS[tag])
        if tag in _ENDS_P:
            close({"p"}, {"button", "td", "th", "table", "article", "div", "section", "body"})
        if tag in ("body", "html") and any(e.tag == tag for e in stack):
            continue
        element = Element(tag)
        if m[3]:
            for name, *values in _ATTRIBUTE.findall(m[3]):
                value = "".join(values)
                if name.lower() == "role":
                    element.role = value.lower()
                else:
                    element.names += f" {value}" if name.lower() in ("class", "id") else ""
        stack[-1].children.append(element)
        if tag in _VOID:
            continue
        if tag in _RAW or tag in _RCDATA:
            end = re.compile(rf"</{re.escape(tag)}(?=[\s/>])[^>]*>?", re.I).search(text, at)
            element.children.append(text[at : end.start() if end else len(text)])
            at = end.end() if end else len(text)
            continue
        if not m[3].rstrip().endswith("/") or tag in _BLOCK:
            stack.append(element)
    else:
        return _digested(root)
    if at < len(text):
        stack[-1].children.append(text[at:])
    return _digested(root)


def _digested(root: Element) -> Element:
    """Hash and weigh every subtree, children first, without recursion."""
    order, todo = [], [root]
    while todo:
        e = todo.pop()
        order.append(e)
        todo += [c for c in e.children if not isinstance(c, str)]
    for e in reversed(order):
        h = xxhash.xxh64(f"{e.tag}\x1f{e.names}\x1f{e.role}")
        for c in e.children:
            if isinstance(c, str):
                c = " ".join(c.split())
                e.weight += len(c)
                h.update(b"\x1d" + c.encode("utf-8", "surrogatepass"))
            else:
                e.weight += c.weight
                h.update(b"\x1e" + c.digest.to_bytes(8, "little"))
        e.digest = h.intdigest()
    return root


def _declared(e: Element, inside: bool) -> bool:
    """Whether an element says that it is not main text; ``inside``: within the main element."""
    if e.tag in _NOT_TEXT or e.role in _NOT_TEXT_ROLE or e.tag == "header" and not inside:
        return True
    if not e.names or e.tag in ("article", "main", "body", "html"):
        return False
    names = e.names.lower()
    if not _NOT_TEXT_WORD.isdisjoint(names.split()):
        return True
    if inside and e.tag not in _CONTAINER:
        return False
    return not (_PLAIN_WORD if inside else _NOT_TEXT_WORD).isdisjoint(_NAME_WORD.findall(names))


def _kept(e: Element, inside: bool) -> bool:
    """In place of ``_declared``: only what is never text goes."""
    return e.tag in _RAW or e.tag in ("head", "template", "textarea", "title")


def _elements(root: Element, skip=lambda e, inside: False):
    """Elements in page order with whether they are inside article or main; skipped subtrees are not entered."""
    todo = [(root, False)]
    while todo:
        e, inside = todo.pop()
        if skip(e, inside):
            continue
        yield e, inside
        inside = inside or e.tag in ("article", "main") or e.role == "main"
        todo += [(c, inside) for c in reversed(e.children) if not isinstance(c, str)]


def main_element(root: Element, skip) -> Element:
    best = {}
    for e, _ in _elements(root, skip):
        kind = "article" if e.tag == "article" else "main" if e.tag == "main" or e.role == "main" else "body" if e.tag == "body" else ""
        if kind and (kind not in best or e.weight > best[kind].weight):
            best[kind] = e
    return best.get("article") or best.get("main") or best.get("body") or root


def _ancestors(root: Element, of: Element) -> set[int]:
    todo, path = [(root, False)], []
    while todo:
        e, leave = todo.pop()
        if leave:
            path.pop()
        elif e is of:
            break
        else:
            path.append(id(e))
            todo += [(e, True), *((c, False) for c in reversed(e.children) if not isinstance(c, str))]
    return set(path)


def candidates(root: Element) -> tuple[int, list[Element], list[Element]]:
    """The main content's hash, and the subtrees that may be template outside and inside the main element."""
    main = main_element(root, _declared)
    semantic = main.tag in ("article", "main") or main.role == "main"
    held = {id(e) for e, _ in _elements(main)} if semantic else set()
    around = _ancestors(root, main) if semantic else set()
    outside, inside = [], []
    for e, _ in _elements(root):
        if e.tag in _BLOCK and e.weight and e.tag not in ("html", "body", "article", "main") and e is not main:
            if id(e) in held:
                if e.tag in _CONTAINER and 2 * e.weight < main.weight:
                    inside.append(e)
            elif id(e) not in around:
                outside.append(e)
    return main.digest if semantic else root.digest, outside, inside


def doomed(root: Element, template: Collection[int], inside: Collection[int]) -> dict[int, Element]:
    """By id, the subtrees whose hashes are in ``template`` or, in the main element, in ``inside``."""
    if not template and not inside:
        return {}
    _, out, within = candidates(root)
    return {id(e): e for part, hashes in ((out, template), (within, inside)) for e in part if e.digest in hashes}


def extract(root: Element, template: Collection[int] = (), inside: Collection[int] = (), declared: bool = True) -> str:
    """The main text of a parsed page without its template subtrees."""
    return _text(root, doomed(root, template, inside), declared)


def _text(root: Element, gone: dict[int, Element], declared: bool) -> str:
    says = _declared if declared else _kept

    def skip(e: Element, inside: bool) -> bool:
        return id(e) in gone or says(e, inside)

    main = main_element(root, skip) if declared else next((e for e, _ in _elements(root) if e.tag == "body"), root)
    blocks, now = [], []

    def flush():
        block = " ".join(entities.unescape("".join(now)).split())
        if block:
            blocks.append(block)
        now.clear()

    todo: list = [(main, main.tag in ("article", "main") or main.role == "main", False)]
    while todo:
        e, inside, leave = todo.pop()
        if leave:
            flush()
        elif isinstance(e, str):
            now.append(e)
        elif e is main or not skip(e, inside):
            if e.tag == "br":
                now.append(" ")
                continue
            if e.tag in _BLOCK:
                flush()
                todo.append((e, inside, True))
            inside = inside or e.tag in ("article", "main") or e.role == "main"
            todo += [(c, inside, False) for c in reversed(e.children)]
    flush()
    return "\n".join(blocks)


def outermost(root: Element, gone: dict[int, Element]) -> int:
    """How many of the subtrees do not lie in another one."""
    count = 0

    def skip(e: Element, _: bool) -> bool:
        nonlocal count
        count += id(e) in gone
        return id(e) in gone

    for _ in _elements(root, skip) if gone else ():
        pass
    return count


_HOST = r"^(?:[A-Za-z][A-Za-z0-9+.-]*:)?//(?:[^/?#@]*@)?([^/?#:]*)"


def host() -> F.Column:
    return F.lower(F.regexp_extract(F.coalesce("url", F.lit("")), _HOST, 1))


def page_key() -> F.Column:
    """Copies of a page on a host share a key: what is deleted from them is the same."""
    return F.xxhash64(host(), "html")


def _signed(v: int) -> int:
    return v - (1 << 64) if v >> 63 else v


def subtrees(pages: DataFrame) -> DataFrame:
    """key, host, content, hashes, inside: one row per page with its candidate subtrees outside and inside the main element."""
    hashes = pa.list_(pa.int64())
    schema = pa.schema([("key", pa.int64()), ("host", pa.string()), ("content", pa.int64()), ("hashes", hashes), ("inside", hashes)])

    def make():
        def one(key, name, html):
            content, *found = candidates(parse(html or ""))
            return ((key, name, _signed(content), *(list({_signed(e.digest) for e in part}) for part in found)),)

        return one

    return pages.select(page_key().alias("key"), host().alias("host"), "html").mapInArrow(
        common.per_row(["key", "host", "html"], schema, make), "key long, host string, content long, hashes array<long>, inside array<long>"
    )


def templates(trees: DataFrame, min_pages: int = MIN_PAGES, inside_share: float = INSIDE_SHARE) -> DataFrame:
    """host, hash, within: the subtrees that recur on enough differing pages of the host; ``within``: those inside main elements.

    Counted in two steps that combine before their shuffles; no host's pages are gathered.
    """
    each = F.expr("explode(concat(transform(hashes, h -> struct(h AS hash, false AS within)), transform(inside, h -> struct(h AS hash, true AS within))))")
    counted = (
        trees.select("host", "content", each.alias("e")).select("host", "content", "e.hash", "e.within").distinct()
        .groupBy("host", "hash", "within").agg(F.count("*").alias("pages")).filter(F.col("pages") >= min_pages)
    )
    sizes = trees.select(F.col("host").alias("of"), "content").distinct().groupBy("of").agg(F.count("*").alias("all"))
    often = ~F.col("within") | (F.col("pages") >= inside_share * F.col("all"))
    return counted.join(sizes, F.col("host").eqNullSafe(F.col("of"))).filter(often).select("host", "hash", "within")


def main_text(pages: DataFrame, min_pages: int = MIN_PAGES, inside_share: float = INSIDE_SHARE, declared: bool = True) -> DataFrame:
    """page_id, url, text, n_chars, n_template for every row of ``pages`` (columns page_id, url, html).

    n_template counts the subtrees deleted as template, the outermost only. A host's recurring subtrees
    come to its pages as one list; of a host with more than ``HOST_LIST`` of them, each page gets those
    that it has. The lists are written first, so that their size is known: below Spark's threshold they
    are broadcast and no page is shuffled, beyond it pages and lists meet in a join that splits hot hosts.
    """
    trees = common.materialise(subtrees(pages))
    known = common.materialise(templates(trees, min_pages, inside_share))
    size = known.groupBy("host").agg(F.count("*").alias("n"))
    signed = F.struct("hash", "within")
    few = known.join(size.filter(F.col("n") <= HOST_LIST).select("host"), "host").groupBy(F.col("host").alias("of")).agg(F.collect_list(signed).alias("by_host"))
    by_host = common.materialise(few)
    many = known.join(size.filter(F.col("n") > HOST_LIST).select("host"), "host")
    own = trees.join(many.select("host").distinct(), "host", "left_semi").select("key", "host", F.explode(F.array_union("hashes", "inside")).alias("hash"))
    by_page = common.materialise(own.distinct().join(many, ["host", "hash"]).groupBy(F.col("key").alias("of_key")).agg(F.collect_list(signed).alias("by_page")))
    schema = pa.schema([("page_id", pa.int64()), ("url", pa.string()), ("text", pa.string()), ("n_chars", pa.int64()), ("n_template", pa.int64())])

    def run(batches):
        lists: dict[tuple, tuple[set[int], set[int]]] = {}  # of the hosts in one slice

        def sets(column):
            out = []
            for found in column:
                found = found.values if found.is_valid else None
                if found is None or not len(found):
                    out.append(((), ()))
                    continue
                hashes, within = (found.field(k).to_numpy(zero_copy_only=False) for k in (0, 1))
                mark = len(hashes), hashes.tobytes(), within.tobytes()
                if mark not in lists:
                    if len(lists) > 64:
                        lists.clear()
                    plain = hashes.astype("<i8").view("<u8")
                    lists[mark] = set(plain[~within].tolist()), set(plain[within].tolist())
                out.append(lists[mark])
            return out

        for batch in batches:
            for part in common.slices(batch):
                rows = []
                ids, urls, pages_ = (part.column(k).to_pylist() for k in (0, 1, 2))
                for page_id, url, html, a, b in zip(ids, urls, pages_, sets(part.column(3)), sets(part.column(4)), strict=True):
                    root = parse(html or "")
                    out, within = (a[k] or b[k] for k in (0, 1))
                    gone = doomed(root, out, within)
                    text = _text(root, gone, declared)
                    rows.append((page_id, url, text, len(text), outermost(root, gone)))
                yield pa.RecordBatch.from_arrays([pa.array(c, type=f.type) for c, f in zip(list(zip(*rows, strict=True)) or [[]] * 5, schema, strict=True)], schema=schema)

    given = pages.select(F.col("page_id").cast("long").alias("page_id"), "url", "html", page_key().alias("key"), host().alias("host"))
    joined = given.join(by_host, F.col("host").eqNullSafe(F.col("of")), "left").join(by_page, F.col("key") == F.col("of_key"), "left")
    return joined.select("page_id", "url", "html", "by_host", "by_page").mapInArrow(run, "page_id long, url string, text string, n_chars long, n_template long")


def op4_main_text(spark: SparkSession, sf_dir: str) -> DataFrame:
    return main_text(common.table(spark, sf_dir, "pages"))
