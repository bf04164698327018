"""Main text of web pages by wrapper inference: one union-free regular expression of tags for each host.

A page becomes a tree of block elements with text slots; neighbours of one kind fold into repeated items, and repeated
runs of kinds into repeated groups. Pages of one host are aligned one by one: items that one side lacks become optional,
texts that differ become variable slots, texts that never differ stay constants of the template. The wrapper then says
which slots hold the article: on pages with a semantic article or main element those inside it, on others variable slots of
low link density (a text is template only where three different pages have it, copies counted once); slots below menus, headers, footers, side bars, notices, adverts, forms and comments never do. Extraction
matches each page's slots with its host's wrapper, decodes references, joins white space, and joins blocks by line feeds.

Inference is hierarchical: tasks align the pages they read, salted groups of a host align the tasks' wrappers, and one group
for each host aligns the salts' wrappers. A host with a third of all pages is thus spread over all tasks, and no task holds
more than one wrapper for each host that it meets. Wrappers are broadcast while they measure up to a bound, else shuffled.

Defined results: null or empty html gives an empty text; a page without markup is one block; attributes, classes, repeated groups and nesting may be of any size; urls without a host share
one wrapper; equal pages give equal texts; pages of any length are read whole; repeated rows give repeated results.
"""

from __future__ import annotations

import html as html_module
import json
import re
from collections.abc import Iterator
from hashlib import blake2b
from zlib import crc32

import pyarrow as pa
from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

from .common import broadcast_if, cut, ship

# Element kinds.
INLINE = frozenset("a abbr acronym b bdi bdo big cite code data del dfn em font i ins kbd label mark nobr q rb rp rt ruby s samp small span strike strong sub sup time tt u var wbr".split())
VOID = frozenset("area base br col embed hr img input link meta param source track wbr".split())
RAW = frozenset("script style textarea title noscript template iframe noframes xmp svg math object select button audio video canvas".split())
BOILERPLATE = frozenset("head nav footer aside form menu dialog fieldset".split())
CLOSES_P = frozenset("address article aside blockquote div dl fieldset footer form h1 h2 h3 h4 h5 h6 header hr main menu nav ol p pre section table ul".split())
SAME_ENDS = {"li": ("li",), "dt": ("dt", "dd"), "dd": ("dt", "dd"), "tr": ("tr", "td", "th"), "td": ("td", "th"), "th": ("td", "th"), "option": ("option",)}
HOLDERS = frozenset("ul ol menu dl table tbody thead tfoot article section div main body".split())
CUES = frozenset(
    "ad ads adv advert advertisement adsense banner sponsor sponsored promo promotion menu nav navbar navigation breadcrumb breadcrumbs sidebar side footer header masthead toolbar cookie cookies consent gdpr notice notices alert popup modal overlay comment comments discussion disqus respond reply replies related recommend recommended share sharing social follow subscribe subscription newsletter signup login search widget widgets pagination pager tags tagcloud copyright legal".split()
)
#: Words that leave a cue what it is inside an article: "share-buttons" is no text of it, "share-price" and "related-work" are.
NEUTRAL = frozenset(
    "0 area article articles bar block box button buttons col container content count entry field form group header footer icon icons inner item items js label left link links list main module new outer page panel post posts right row section site slot small story text thread title tool tools top bottom unit user wrap wrapper".split()
)
MAIN_CUES = frozenset("articlebody article-body post-content entry-content post-body article-content main-content".split())

#: A tag ends outside quotes; where quotes do not close before the page ends, tags end at the next angle bracket from there on.
_SHARED = r"""<!--.*?(?:-->|\Z)|%s<[!?/][^>]*>|<(/?)([a-zA-Z][^\s/>]*)([^>]*)>|[^<]++|<"""
TOKEN = re.compile(_SHARED % r"""<(/?)([a-zA-Z][^\s/>]*)((?:[^>"']++|"[^"]*+"|'[^']*+')*+)>|""", re.DOTALL)
PLAIN = re.compile(_SHARED % "()()()(?!)|", re.DOTALL)
REPEAT = re.compile(r"(.{2,}?)\1+", re.DOTALL)
ATTR = re.compile(r"""(class|id|role|itemprop|hidden|aria-hidden)(?:\s*=\s*(?:"([^"]*)"|'([^']*)'|([^\s"'>]+)))?""", re.IGNORECASE)
SPACE = re.compile(r"\s+")
HOST = r"^[A-Za-z][A-Za-z0-9+.-]*://(?:[^/?#@]*@)?([^/:?#]+)"
SALTS = 32
#: Wrappers of all hosts together are broadcast up to this many characters.
BROADCAST_CHARS = 32_000_000
MOST_NAMES = 6
#: Elements nested deeper stand side by side at this depth; their texts, order and kinds (menu, article) are kept.
DEEPEST = 300
#: A text that never differs is template if so many different pages have it.
TEMPLATE_PAGES = 3

Node = list  # [symbol, children]; a text is [None, text, linked characters]
Item = list  # [symbol, optional, repeated, children or None, constant, characters, linked characters, digests of up to TEMPLATE_PAGES pages]


def _symbol(tag: str, attrs: str) -> str:
    """Tag with its sorted classes, id and role; digits are blurred so that numbered ids agree.

    Six names are kept; what the others say (a cue, an unmistakable one, the article, hidden) stays as a mark.
    """
    if not attrs or "=" not in attrs and "hidden" not in attrs:
        return tag
    names = []
    for m in ATTR.finditer(attrs):
        key, value = m[1].lower(), m[2] or m[3] or m[4] or ""
        if key == "hidden" or key == "aria-hidden" and value.lower() == "true":
            names.append("~hidden")
        elif key != "aria-hidden":
            names += re.sub(r"[0-9]+", "0", value.lower()).split()
    names = sorted(set(names))
    kept, others = names[:MOST_NAMES], names[MOST_NAMES:]
    marks = [mark for mark, found in (("~cue", _has_cue(others)), ("~clear", _has_clear_cue(others)), ("~hidden", "~hidden" in others), ("~main", _names_main(others))) if found]
    return ".".join([tag, *kept, *marks])


def _has_cue(names: list[str]) -> bool:
    return any(w in CUES for n in names for w in re.split(r"[-_]+", n))


def _has_clear_cue(names: list[str]) -> bool:
    return any(_has_cue([n]) and all(w in CUES or w in NEUTRAL for w in re.split(r"[-_]+", n)) for n in names)


def _names_main(names: list[str]) -> bool:
    return "main" in names or any(n in MAIN_CUES for n in names)


def parse(page: str) -> Node:
    """Tree of block elements and texts; unclosed and misplaced tags end where browsers end them."""
    root: Node = ["root", []]
    stack, tags = [root], ["root"]
    open_text, linked, in_link = [], 0, False

    def flush() -> None:
        nonlocal linked
        if open_text:
            text = "".join(open_text)
            if not text.isspace():
                node = [None, text, linked]
                symbol, kids, *deep = stack[-1]
                if kids is not None:
                    kids.append(node)
                else:
                    stack[DEEPEST][1].append(["nav" if deep[0] else "main" if deep[1] else symbol, [node]])
            open_text.clear()
            linked = 0

    at, n, last = 0, len(page), page.rfind(">")
    match = TOKEN.match
    while at < n:
        if at > last:  # no tag ends any more
            open_text.append(page[at:])
            if in_link:
                linked += n - at
            break
        m = match(page, at)
        at = m.end()
        tag = m[2] or m[5]
        if m[5]:
            match = PLAIN.match
        if tag is None:
            s = m[0]
            if s[0] != "<" or s == "<":
                open_text.append(s)
                if in_link:
                    linked += len(s)
            continue
        tag, closing = tag.lower(), m[1] or m[4]
        if tag in RAW and not closing:
            end = re.compile(rf"</{re.escape(tag)}\s*>", re.IGNORECASE).search(page, at)
            at = end.end() if end else (n if tag in ("script", "style") else at)
            continue
        if tag in INLINE:
            if tag == "a":
                in_link = not closing
            continue
        flush()
        if tag in VOID:
            continue
        if closing:
            in_link = False
            if tag in tags:
                while tags.pop() != tag:
                    stack.pop()
                stack.pop()
                if not stack:
                    stack, tags = [root], ["root"]
            continue
        if tag in CLOSES_P and tags[-1] == "p":
            tags.pop()
            stack.pop()
        for k in range(len(tags) - 1, 0, -1) if tag in SAME_ENDS else ():
            if tags[k] in SAME_ENDS[tag]:
                del tags[k:], stack[k:]
                break
            if tags[k] in HOLDERS:
                break
        symbol = _symbol(tag, m[3] or m[6] or "")
        if len(tags) <= DEEPEST:
            node: Node = [symbol, []]
            stack[-1][1].append(node)
        else:
            if len(tags) == DEEPEST + 1:
                inside = any(is_main(x[0]) for x in stack)
                below = False
            else:
                below, inside = stack[-1][2:]
            node = [symbol, None, below or is_boilerplate(symbol, inside), inside or is_main(symbol)]
        stack.append(node)
        tags.append(tag)
    flush()
    return root


def clean(text: str) -> str:
    return SPACE.sub(" ", html_module.unescape(text)).strip()


def page_digest(tree: Node) -> int:
    """Digest of what a page shows, so that copies count as one page."""
    return int.from_bytes(blake2b(repr(tree).encode("utf-8", "replace"), digest_size=6).digest())


def generalise(node: Node, page: int | None = None) -> Item:
    """A page's own wrapper: runs of one kind are repeated items, runs of kinds are repeated groups."""
    page = page_digest(node) if page is None else page
    kids: list[Item] = []
    for c in node[1]:
        if c[0] is None:
            text = clean(c[1])
            item = ["#", False, False, None, crc32(text.encode("utf-8", "replace")), len(c[1]), c[2], [page]]
        else:
            item = generalise(c, page)
        if kids and kids[-1][0] == item[0]:
            kids[-1] = merge(kids[-1], item)
            kids[-1][2] = True
        else:
            kids.append(item)
    return [node[0], False, False, fold(kids), None, 0, 0, [page]]


def fold(kids: list[Item]) -> list[Item]:
    """Adjacent repeats of a run of kinds, of any length, become one repeated group."""
    if len(kids) < 4:
        return kids
    codes: dict[str, int] = {}
    line = "".join([chr(0x10000 + codes.setdefault(k[0], len(codes))) for k in kids])
    out, at = [], 0
    for m in REPEAT.finditer(line):
        group, period = kids[m.start() : m.end(1)], len(m[1])
        for j in range(m.end(1), m.end(), period):
            group = [merge(x, y) for x, y in zip(group, kids[j : j + period], strict=True)]
        out += [*kids[at : m.start()], ["(" + " ".join(k[0] for k in group) + ")", False, True, group, None, 0, 0, []]]
        at = m.end()
    return [*out, *kids[at:]]


def merge(a: Item, b: Item) -> Item:
    """One item for both."""
    pages = a[7] if a[7] == b[7] else sorted({*a[7], *b[7]})[:TEMPLATE_PAGES]
    if a[3] is None:
        return [a[0], a[1] or b[1], a[2] or b[2], None, a[4] if a[4] == b[4] else None, a[5] + b[5], a[6] + b[6], pages]
    return [a[0], a[1] or b[1], a[2] or b[2], align(a[3], b[3]), None, 0, 0, pages]


def _as_group(kids: list[Item], group: Item) -> list[Item]:
    """Single occurrences of another wrapper's group, as that group."""
    own = group[0][1:-1].split(" ")
    for i in range(len(kids) - len(own) + 1):
        if [k[0] for k in kids[i : i + len(own)]] == own:
            return [*kids[:i], [group[0], False, False, kids[i : i + len(own)], None, 0, 0, []], *kids[i + len(own) :]]
    return kids


def align(a: list[Item], b: list[Item]) -> list[Item]:
    """Common items in order, those of one side alone as optional ones."""
    left, right = [k[0] for k in a], [k[0] for k in b]
    if left == right:
        return [merge(x, y) for x, y in zip(a, b, strict=True)]
    for group in [k for k in a if k[0][0] == "(" and k[0] not in right]:
        b = _as_group(b, group)
    for group in [k for k in b if k[0][0] == "(" and k[0] not in left]:
        a = _as_group(a, group)
    left, right = [k[0] for k in a], [k[0] for k in b]
    best = [[0] * (len(b) + 1) for _ in range(len(a) + 1)]
    for i in range(len(a) - 1, -1, -1):
        for j in range(len(b) - 1, -1, -1):
            best[i][j] = best[i + 1][j + 1] + 1 if left[i] == right[j] else max(best[i + 1][j], best[i][j + 1])
    out, i, j = [], 0, 0
    while i < len(a) or j < len(b):
        if i < len(a) and j < len(b) and left[i] == right[j]:
            item, i, j = merge(a[i], b[j]), i + 1, j + 1
        elif j == len(b) or i < len(a) and best[i + 1][j] >= best[i][j + 1]:
            item, i = [a[i][0], True, *a[i][2:]], i + 1
        else:
            item, j = [b[j][0], True, *b[j][2:]], j + 1
        if out and out[-1][0] == item[0]:
            out[-1] = merge(out[-1], item)
            out[-1][2] = True
        else:
            out.append(item)
    return out


def expression(item: Item) -> str:
    """The wrapper as a union-free regular expression: slots are (.*), constants *, groups in parentheses, with + and ?."""
    if item[3] is None:
        body = "(.*)" if item[4] is None else "*"
    elif item[0][0] == "(":
        body = "(" + " ".join(map(expression, item[3])) + ")"
    else:
        body = f"<{item[0]}>" + " ".join(map(expression, item[3])) + "</>"
    return body + ("+" if item[2] else "") + ("?" if item[1] else "")


def is_boilerplate(symbol: str, inside_main: bool) -> bool:
    tag, *names = symbol.split(".")
    if tag in BOILERPLATE or tag == "header" and not inside_main or "~hidden" in names:
        return True
    if tag in ("article", "main", "body", "root"):
        return False
    return "~clear" in names or _has_clear_cue(names) if inside_main else "~cue" in names or _has_cue(names)


def is_main(symbol: str) -> bool:
    tag, *names = symbol.split(".")
    return tag in ("article", "main") or "~main" in names or _names_main(names)


def content_rule(wrapper: Item) -> dict:
    """``main``: where texts of an article element stand; ``paths``: where those of pages without one stand;
    ``drop``: checksums of template texts that stand there too."""
    slots: list[tuple[str, bool, Item]] = []

    def walk(item: Item, path: str, main: bool) -> None:
        for k in item[3]:
            if k[3] is None:
                slots.append((path, main, k))
            elif k[0][0] == "(":
                walk(k, path, main)
            elif not is_boilerplate(k[0], main):
                walk(k, f"{path}/{k[0]}", main or is_main(k[0]))

    walk(wrapper, "root", False)
    fixed = lambda k: k[4] is not None and len(k[7]) >= TEMPLATE_PAGES
    linked = lambda k: k[6] * 2 > k[5]
    other = [(p, k) for p, main, k in slots if not main]
    good = {p for p, k in other if not fixed(k) and not linked(k)}
    return {"main": sorted({p for p, main, _ in slots if main}), "paths": sorted(good), "drop": sorted({k[4] for _, k in other if fixed(k)})}


def extract(page: str | None, rule: dict | None) -> str:
    """Text of one page under its host's rule (None: the page is its own host)."""
    if not page:
        return ""
    tree = parse(page)
    rule = rule or content_rule(generalise(tree))
    main, paths, drop = set(rule["main"]), set(rule["paths"]), set(rule["drop"])
    article, out, has_main = [], [], False
    work: list[tuple[Node, str, bool, bool]] = [(tree, "root", False, False)]
    while work:
        node, path, inside, below = work.pop()
        if node[0] is None:
            text = clean(node[1])
            if text and path in main:
                article.append(text)
            elif text and path in paths and not (drop and crc32(text.encode("utf-8", "replace")) in drop):
                out.append(text)
            continue
        below = below or is_boilerplate(node[0], inside)
        inside = inside or not below and is_main(node[0])
        has_main = has_main or inside
        work += [(c, path if c[0] is None else f"{path}/{c[0]}", inside, below) for c in reversed(node[1])]
    return "\n".join(article if has_main else out)


def host_of(url: Column) -> Column:
    return F.lower(F.coalesce(F.regexp_extract(url, HOST, 1), F.lit("")))


def infer_wrappers(pages: DataFrame, url_col: str = "url", html_col: str = "html") -> DataFrame:
    """``host, pages, wrapper`` (JSON of the aligned items) for every host, over all its pages."""
    ship(pages.sparkSession)
    kinds = "host string, salt int, wrapper string"

    def emit(held: dict[str, Item], salt: int) -> pa.RecordBatch:
        return pa.RecordBatch.from_arrays([pa.array(list(held), pa.string()), pa.array([salt] * len(held), pa.int32()), pa.array([json.dumps(w, separators=(",", ":")) for w in held.values()], pa.string())], names=["host", "salt", "wrapper"])

    def read(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        from pyspark import TaskContext

        salt = TaskContext.get().partitionId() % SALTS
        held: dict[str, Item] = {}
        for batch in batches:
            for host, page in zip(batch.column(0).to_pylist(), batch.column(1), strict=True):
                if p := page.as_py():
                    own = generalise(parse(p))
                    held[host] = merge(held[host], own) if host in held else own
                    if len(held) >= 2_000:
                        yield emit(held, salt)
                        held = {}
        yield emit(held, salt)

    def together(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        """Rows come sorted by host and salt, so one wrapper is held at a time."""
        key, held = None, None
        for batch in batches:
            for host, salt, w in zip(*(c.to_pylist() for c in batch.columns), strict=True):
                if key is not None and (host, salt) != key:
                    yield emit({key[0]: held}, key[1])
                    held = None
                key = (host, salt)
                held = json.loads(w) if held is None else merge(held, json.loads(w))
        if key is not None:
            yield emit({key[0]: held}, key[1])

    partial = pages.select(host_of(F.col(url_col)).alias("host"), html_col).mapInArrow(read, kinds)
    salted = partial.repartition("host", "salt").sortWithinPartitions("host", "salt", "wrapper").mapInArrow(together, kinds)
    whole = salted.select("host", F.lit(0).alias("salt"), "wrapper").repartition("host").sortWithinPartitions("host", "wrapper").mapInArrow(together, kinds)
    return whole.select("host", "wrapper")


def extract_pages(pages: DataFrame, id_col: str = "page_id", url_col: str = "url", html_col: str = "html", wrappers: DataFrame | None = None) -> DataFrame:
    """``id_col, url_col, text`` for each page, by the wrapper of its host."""
    ship(pages.sparkSession)
    schema = pa.schema([("host", pa.string()), ("rule", pa.string())])

    def rules(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in batches:
            found = [json.dumps(content_rule(json.loads(w)), separators=(",", ":")) for w in batch.column(1).to_pylist()]
            yield pa.RecordBatch.from_arrays([batch.column(0), pa.array(found, pa.string())], schema=schema)

    known = cut((wrappers or infer_wrappers(pages, url_col, html_col)).mapInArrow(rules, "host string, rule string"))
    size = known.agg(F.coalesce(F.sum(F.length("rule") + F.length("host")), F.lit(0))).first()[0]
    rows = pages.select(F.col(id_col).alias("id"), F.col(url_col).alias("url"), F.col(html_col).alias("html"), host_of(F.col(url_col)).alias("host"))
    rows = rows.join(broadcast_if(known, size, BROADCAST_CHARS), "host", "left").select("id", "url", "html", "rule")

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        parsed: dict[str | None, dict | None] = {None: None}
        for batch in batches:
            texts = []
            for page, rule in zip(batch.column(2), batch.column(3).to_pylist(), strict=True):
                if rule not in parsed:
                    if len(parsed) > 2_000:
                        parsed = {None: None}
                    parsed[rule] = json.loads(rule)
                texts.append(extract(page.as_py(), parsed[rule]))
            yield pa.RecordBatch.from_arrays([batch.column(0), batch.column(1), pa.array(texts, pa.string())], names=[id_col, url_col, "text"])

    kind = pages.schema[id_col].dataType.simpleString()
    return rows.mapInArrow(run, f"`{id_col}` {kind}, `{url_col}` string, text string")
