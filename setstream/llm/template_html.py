"""Main text of web pages, by the template that the pages of a host share.

Tokens are elements, told apart by the chain of tags and class names above them, and blocks of text, told apart by element and words.
For every host, tokens with the same occurrence vector over its distinct pages form a class; vectors are compared by fingerprints that add up
over partitions, so no page is ever brought to another. A class is large and frequent if it has two tokens at least on enough
pages. It is valid if it is ordered (its elements keep their order among their siblings) and nested (all of it lies in one slot of the classes
accepted before it; the first is the class that every page has once). The valid classes' elements are the template, and what varies between them
fills its slots.

The slots decide. The article's slot is the one with most varying unlinked text (if the template has an article or main element: inside it), and its
element is the container. The container's text is the page's, without
- template text: blocks that most of the host's distinct pages repeat there;
- menus: slots below the container that are links nearly throughout;
- lists of records: repeated classes of several elements with text of their own, such as readers' remarks with a name and a date;
a varying heading that stands before the container goes with it. Of markup only what HTML or a page says outright is used beside that: head,
menu, aside, footer and form elements and their roles, hidden elements, and names that say that readers comment. On pages without a
template (fewer distinct pages than ``LEAST_PAGES``) or without their host's container, further names mark what isn't article text.

Edge cases: null and empty pages give the empty text; null and odd urls share the host ''; unclosed and stray tags, comments and truncated
pages are read as browsers do where it matters; repeated pages and url variants count once; very long and deep pages are read whole; an empty table
gives an empty result; extra columns are ignored.
"""

from __future__ import annotations

import html as _html
import re
from collections.abc import Iterator
from typing import NamedTuple

import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from .runtime import materialise

_TOKEN = re.compile(
    r"<!--.*?(?:-->|\Z)|<(?P<raw>script|style|noscript|template|textarea|iframe|svg|select|button|object|audio|video|canvas)\b[^>]*>.*?(?:</(?P=raw)\s*>|\Z)"
    r"|<(?P<end>/?)(?P<tag>[a-zA-Z][a-zA-Z0-9:-]*)(?P<attrs>(?:[^<>\"']|\"[^\"]*\"|'[^']*')*)>|<[!?/a-zA-Z][^>]*(?:>|\Z)|(?P<text>[^<]+|<)",
    re.S | re.I,
)
_ATTR = re.compile(r"""\b(class|id|role|hidden|aria-hidden|style)\b(?:\s*=\s*(?:"([^"]*)"|'([^']*)'|([^\s>]+)))?""", re.I)
_SPACE = re.compile(r"\s+")
_PARTS = re.compile(r"[^a-z]+")
#: Numbers in class names that tell pages apart, not kinds of elements.
_NUMBERS = re.compile("[0-9]{2,}")

# What HTML means by these names.
BLOCKS = frozenset(
    "address article aside blockquote body caption center dd details dialog div dl dt fieldset figcaption figure footer form h1 h2 h3 h4 h5 h6 "
    "head header hr html legend li main menu nav ol p pre section summary table tbody td tfoot th thead title tr ul".split()
)
VOID = frozenset("area base br col embed hr img input link meta param source track wbr".split())
CONTAINERS = frozenset("article body div main section td".split())
DROPPED_TAGS = frozenset("aside dialog footer form head header menu nav title".split())
DROPPED_ROLES = frozenset("alert alertdialog banner complementary contentinfo dialog form menu menubar navigation search toolbar".split())
DROPPED_NAMES = frozenset(
    "ad ads adsense advert advertisement adverts alert aside banner breadcrumb breadcrumbs byline comment comments consent cookie cookies copyright disclaimer "
    "discussion disqus footer form gdpr header login masthead menu modal nav navbar navigation newsletter notice notices notification overlay pager pagination "
    "popup promo promoted promotion recommended related replies reply respond search share sharing sidebar signup skip social sponsor sponsored subscribe "
    "toolbar widget".split()
)
KEPT_NAMES = frozenset("article body content entry main post story text".split())
COMMENT_NAMES = frozenset("comment comments discussion disqus replies reply respond".split())
#: Tags that end an open element of the same family.
CLOSES = {"li": ("li",), "dt": ("dt", "dd"), "dd": ("dt", "dd"), "tr": ("tr", "td", "th"), "td": ("td", "th"), "th": ("td", "th")}
ARTICLES = ("article", "main")
HEADINGS = ("h1", "h2")
#: Elements that are one unit of running text or of a table; a repeated class of these alone is no list of records.
UNITS = frozenset("p h1 h2 h3 h4 h5 h6 li dt dd blockquote pre figure figcaption table tbody thead tfoot tr td th caption details summary".split())

#: A class is large with so many tokens, frequent on so many distinct pages and such a share of its host's.
LEAST_TOKENS, LEAST_PAGES, LEAST_SHARE = 2, 3, 0.3
#: Blocks of text are template text on such a share of a host's distinct pages.
CONSTANT_SHARE = 0.6
#: Elements whose order among their siblings turns on more than this share of their pages are out of order.
TURNED = 0.1
#: A slot is a menu if such a share of its text is linked.
MENU_SHARE = 0.9
#: Without template text a page whose article is template text keeps less than this share of its text: it is a near copy.
LEAST_REST = 0.2
#: Templates, and counts of pages by host, that are broadcast at once, in bytes; more are joined by shuffle.
BROADCAST_BYTES = 8 << 20


def _dropped(tag: str, attrs: dict[str, str]) -> tuple[int, int]:
    """By what HTML and the page say outright, and by all names. 0: kept; 1: not article text, unless an article opens inside; 2: never article text."""
    names = {n for n in _PARTS.split(f"{attrs.get('class', '')} {attrs.get('id', '')}".lower()) if n}
    role = attrs.get("role", "").lower()
    hidden = "hidden" in attrs or attrs.get("aria-hidden") == "true" or re.search(r"display\s*:\s*none|visibility\s*:\s*hidden", attrs.get("style", ""), re.I)
    if hidden or (names & COMMENT_NAMES and tag != "body"):
        return 2, 2
    if tag in ("body", "html") or _is_article(tag, attrs):
        return 0, 0
    if tag in DROPPED_TAGS or role in DROPPED_ROLES:
        return 1, 1
    return 0, int(bool(names & DROPPED_NAMES and not names & KEPT_NAMES))


def _is_article(tag: str, attrs: dict[str, str]) -> bool:
    return tag in ARTICLES or attrs.get("role", "").lower() in ("main", "article")


class Block(NamedTuple):
    node: int
    kept: bool
    named: bool  # kept by names too
    chars: int
    linked: int
    text: str


class Page:
    """The page's elements as nodes, one for each chain of tags and names: ``up`` is a node's parent, ``key`` a hash of its chain, ``label`` its
    tag and name, ``opened`` how often it opens, ``before`` the sibling node that first opened before it (-1: none). Nodes come in
    order of first opening, so parents come first. ``runs``: (node, kept, kept by names, linked, text, block) of every run of text."""

    def __init__(self, source: str):
        import xxhash

        self.up, self.key, self.label, self.opened, self.before, self.article = [0], [0], [""], [1], [-1], [False]
        self.runs: list[tuple[int, bool, bool, bool, str, int]] = []
        known: dict[tuple[int, str], int] = {}
        latest: dict[int, int] = {}
        # Open elements: (tag, node, kept, kept by names, inside an article). Headers inside an article hold its title and stay.
        stack: list[tuple[str, int, bool, bool, bool]] = [("", 0, True, True, False)]
        depth: dict[str, int] = {}  # open elements by tag
        links = block = 0

        def cut(i: int) -> None:
            for entry in stack[i:]:
                depth[entry[0]] -= 1
            del stack[i:]

        for m in _TOKEN.finditer(source):
            text = m["text"]
            if text is not None:
                _, node, kept, named, _ = stack[-1]
                self.runs.append((node, kept, named, links > 0, text, block))
                continue
            tag = m["tag"]
            if tag is None:
                continue
            tag = tag.lower()
            if m["end"]:
                if tag == "a":
                    links = 0
                if tag in BLOCKS:
                    block += 1
                    if depth.get(tag):
                        i = len(stack) - 1
                        while stack[i][0] != tag:
                            i -= 1
                        cut(i)
                continue
            if tag == "br":
                self.runs.append((stack[-1][1], stack[-1][2], stack[-1][3], False, " ", block))
                continue
            if tag == "a":
                links = 1
            if tag not in BLOCKS:
                continue
            block += 1
            links = 0
            if tag in VOID:
                continue
            ended = CLOSES.get(tag)
            for i in range(len(stack) - 1, 0, -1):
                if stack[i][0] == "p" or (ended and stack[i][0] in ended):
                    cut(i)
                elif stack[i][0] not in ("tbody", "thead", "tfoot"):
                    break
            attrs = {k.lower(): a or b or c for k, a, b, c in _ATTR.findall(m["attrs"])} if m["attrs"] else {}
            if tag in ("nav", "footer", "article", "main", "body") and stack[-1][0] == "head":
                cut(len(stack) - 1)
            _, up, kept, named, inside = stack[-1]
            name = _NUMBERS.sub("#", attrs["class"]) if attrs.get("class") else re.sub("[0-9]+", "#", attrs.get("id") or "")
            label = f"{tag}.{name.strip().lower()}" if name else tag
            article = _is_article(tag, attrs)
            node = known.get((up, label))
            if node is None:
                node = known[up, label] = len(self.up)
                self.up.append(up)
                self.key.append(xxhash.xxh64_intdigest(label, self.key[up] % (1 << 64)) - HALF)
                self.label.append(label)
                self.opened.append(0)
                self.before.append(latest.get(up, -1))
                self.article.append(article)
                latest[up] = node
            self.opened[node] += 1
            drop, drop_named = _dropped(tag, attrs)
            if tag == "header" and inside and drop == 1:
                drop = drop_named = 0
            fresh = article and not inside
            stack.append((tag, node, drop == 0 and (kept or fresh), drop_named == 0 and (named or fresh), inside or article))
            depth[tag] = depth.get(tag, 0) + 1

    def blocks(self) -> list[Block]:
        """Every block with text, in page order: white space as one space, references decoded."""
        out: dict[int, list] = {}
        for node, kept, named, linked, text, block in self.runs:
            at = out.setdefault(block, [node, kept, named, 0, []])
            at[3] += len(text) * linked
            at[4].append(text)
        made = []
        for node, kept, named, linked, parts in out.values():
            text = _SPACE.sub(" ", _html.unescape("".join(parts))).strip()
            if text:
                made.append(Block(node, kept, named, len(text), min(linked, len(text)), text))
        return made

    def within(self, keys: set[int]) -> list[bool]:
        """For each node whether it or a node above it is one of ``keys``."""
        out = [self.key[0] in keys]
        for node in range(1, len(self.up)):
            out.append(out[self.up[node]] or self.key[node] in keys)
        return out

    def own_article(self) -> set[int]:
        """The outermost article or main element that opens first; of a page without one, the page."""
        inside = [False]
        for node in range(1, len(self.up)):
            inside.append(inside[self.up[node]] or self.article[node])
        outer = [n for n in range(1, len(self.up)) if self.article[n] and not inside[self.up[n]]]
        return {self.key[min(outer, key=self._depth)] if outer else self.key[0]}

    def _depth(self, node: int) -> int:
        n = 0
        while node:
            node, n = self.up[node], n + 1
        return n


HALF = 1 << 63


def text_hash(text: str) -> int:
    import xxhash

    return xxhash.xxh64_intdigest(text) - HALF


def host_of(url):
    return F.coalesce(F.lower(F.regexp_extract(url, r"^[A-Za-z][A-Za-z0-9+.-]*://(?:[^/?#@]*@)?([^/?#]*)", 1)), F.lit(""))


#: Rows that pages give: kinds are page, element, text and order (``token``: the sibling that opened before ``key``).
TOKENS = "host string, page long, kind string, key long, up long, label string, article boolean, token long, n long, chars long, linked long, own long, place long"
_NAMES = [c.split()[0] for c in TOKENS.split(", ")]
ARROW = pa.schema([(n, {"string": pa.string(), "boolean": pa.bool_()}.get(t, pa.int64())) for n, t in (c.split() for c in TOKENS.split(", "))])


def page_tokens(source: str) -> list[tuple]:
    """Rows of one page, without its host. Counts of characters are of text that HTML itself does not keep apart; an element's ``chars`` and
    ``linked`` are of all text inside it, ``own`` of unlinked text directly in it. ``page`` is a hash of the text of the
    page's article, so that copies and url variants of one page have one."""
    page = Page(source)
    blocks = [b for b in page.blocks() if b.kept]
    size = len(page.up)
    chars, linked, own = [0] * size, [0] * size, [0] * size
    for b in blocks:
        chars[b.node] += b.chars
        linked[b.node] += b.linked
        own[b.node] += b.chars - b.linked
    for node in range(size - 1, 0, -1):
        chars[page.up[node]] += chars[node]
        linked[page.up[node]] += linked[node]
    inside = page.within(page.own_article())
    name = text_hash("\n".join(b.text for b in blocks if b.named and inside[b.node]))
    rows = [(name, "page", 0, 0, "", False, 0, 1, chars[0], linked[0], 0, 0)]
    for n in range(1, size):
        key, up = page.key[n], page.key[page.up[n]]
        rows.append((name, "element", key, up, page.label[n], page.article[n], 0, page.opened[n], chars[n], linked[n], own[n], n))
        if page.before[n] >= 0:
            rows.append((name, "order", key, up, "", False, page.key[page.before[n]], 1, 0, 0, 0, 0))
    texts: dict[tuple[int, int], list[int]] = {}
    for b in blocks:
        at = texts.setdefault((page.key[b.node], text_hash(b.text)), [0, 0, 0])
        at[0] += 1
        at[1] += b.chars
        at[2] += b.linked
    rows += [(name, "text", key, 0, "", False, token, n, c, link, c - link, 0) for (key, token), (n, c, link) in texts.items()]
    return rows


def _tokens(pages: DataFrame) -> DataFrame:
    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in batches:
            # Rows of copies in one batch leave once.
            rows: dict[tuple, None] = {}
            for host, source in zip(batch.column(0).to_pylist(), batch.column(1).to_pylist(), strict=True):
                for row in page_tokens(source or ""):
                    rows[host, *row] = None
            columns = list(zip(*rows)) if rows else [()] * len(_NAMES)
            yield pa.RecordBatch.from_arrays([pa.array(c, f.type) for c, f in zip(columns, ARROW, strict=True)], schema=ARROW)

    return pages.select("host", "html").mapInArrow(run, TOKENS)


class Template(NamedTuple):
    """What a host's pages share: ``container``, ``slot`` (the element with most text directly in it), ``titles`` and ``dropped`` elements
    by key, ``constant`` blocks by hash, and the template's elements in order, as (label, depth)."""

    container: int
    slot: int
    titles: list[int]
    dropped: list[int]
    constant: list[int]
    outline: list[tuple[str, int]]


def deduce(pages: int, vector: int, elements: list[dict], orders: list[dict], texts: list[dict]) -> Template | None:
    """The template of one host from its frequent tokens, whose number the length of its pages bounds. ``vector`` is that of a token which every page
    has once."""
    of = {e["key"]: e for e in elements}
    # Ordered: an element doesn't open both before and after a sibling.
    turned: dict[int, int] = {}
    for o in orders:
        first, then = of.get(o["token"]), of.get(o["key"])
        if first and then and first["place"] / first["pages"] > then["place"] / then["pages"]:
            turned[o["key"]] = turned.get(o["key"], 0) + o["pages"]
    ordered = {k for k, e in of.items() if turned.get(k, 0) <= TURNED * e["pages"]}
    constant = [t for t in texts if t["pages"] >= CONSTANT_SHARE * pages]
    classes: dict[tuple[int, int], list[int]] = {}
    size: dict[tuple[int, int], int] = {}
    for e in elements:
        if e["key"] in ordered:
            classes.setdefault((e["pages"], e["vector"]), []).append(e["key"])
    for t in [*elements, *constant]:
        size[t["pages"], t["vector"]] = size.get((t["pages"], t["vector"]), 0) + 1
    template: set[int] = set()

    def slot_of(key: int) -> int | None:
        """The accepted element around ``key``; None if a node above is not among the frequent ones."""
        key = of[key]["up"]
        while key and key not in template:
            if key not in of:
                return None
            key = of[key]["up"]
        return key

    root = (pages, vector)
    repeated: list[list[int]] = []
    for name in sorted(classes, key=lambda c: (c != root, -c[0], min(of[k]["place"] / of[k]["pages"] for k in classes[c]))):
        keys = classes[name]
        if size[name] < LEAST_TOKENS:
            continue
        # Nested: what is uppermost in the class lies in one slot.
        if name != root and len({slot_of(k) for k in keys if of[k]["up"] not in keys}) != 1:
            continue
        template.update(keys)
        if any(of[k]["most"] > 1 for k in keys):
            repeated.append(keys)
    single = [k for k in template if of[k]["most"] == 1]
    if not single:
        return None
    # Text by element, without template text: of near copies nearly all is template text, and all counts.
    fixed: dict[int, int] = {}
    for t in constant:
        key = t["key"]
        while key in of:
            fixed[key] = fixed.get(key, 0) + t["chars"] - t["linked"]
            key = of[key]["up"]
    top = [k for k in of if of[k]["up"] == 0]
    whole, kept = sum(of[k]["chars"] - of[k]["linked"] for k in top), sum(of[k]["chars"] - of[k]["linked"] - fixed.get(k, 0) for k in top)
    copies = kept < LEAST_REST * whole

    def mass(key: int) -> int:
        return of[key]["chars"] - of[key]["linked"] - (0 if copies else fixed.get(key, 0))

    children: dict[int, list[int]] = {}
    for k, e in of.items():
        children.setdefault(e["up"], []).append(k)

    def below(outer: int) -> dict[int, int]:
        """Elements under ``outer`` and how deep below it."""
        found, todo = {}, [(outer, 0)]
        while todo:
            key, n = todo.pop()
            for k in children.get(key, ()):
                found[k] = n + 1
                todo.append((k, n + 1))
        return found

    records = [k for keys in repeated for k in _records(keys, of)]
    slot_mass = {k: mass(k) for k in single}
    for k in [*single, *records]:
        up = of[k]["up"]
        while up in of and up not in slot_mass:
            up = of[up]["up"]
        if up in slot_mass:
            slot_mass[up] -= mass(k)
    articles = [k for k in single if of[k]["article"] and mass(k) > 0]
    if articles:
        covered = set().union(*(below(k) for k in articles))
        outer = [k for k in articles if k not in covered]
        container = max(outer, key=lambda k: (mass(k), k))
    else:
        container = max(single, key=lambda k: (slot_mass[k], k))
        while of[container]["label"].split(".")[0] not in CONTAINERS and of[container]["up"] in of:
            container = of[container]["up"]
    if mass(container) <= 0:
        return None
    inner = below(container)
    place = {k: of[k]["place"] / of[k]["pages"] for k in of}
    titles = []
    if not any(of[k]["label"].split(".")[0] in HEADINGS for k in inner):
        heads = [k for k in single if of[k]["label"].split(".")[0] in HEADINGS and place[k] < place[container] and mass(k) > 0 and container not in below(k)]
        titles = [max(heads, key=lambda k: place[k])] if heads else []
    menus = [k for k in inner if k in template and of[k]["label"].split(".")[0] not in UNITS and of[k]["linked"] >= MENU_SHARE * of[k]["chars"] > 0]
    dropped = [k for k in inner if k in records or k in menus]
    slot = max(of, key=lambda k: (of[k]["own"], k))

    depth = below(0)
    outline = [(of[k]["label"], depth[k]) for k in sorted(template, key=lambda k: (place[k], k))]
    return Template(container, slot, titles, dropped, sorted({t["token"] for t in constant}), outline)


def _records(keys: list[int], of: dict[int, dict]) -> list[int]:
    """The wrappers of a repeated class: its uppermost elements that hold two other elements of it, at least, with text of their own."""
    out = []
    for k in keys:
        if of[k]["up"] in keys or of[k]["label"].split(".")[0] in UNITS - {"li"}:
            continue
        fields = 0
        for other in keys:
            up = other
            while up != k and up in of:
                up = of[up]["up"]
            fields += other != k and up == k and of[other]["own"] + of[other]["linked"] > 0
        if fields >= 2:
            out.append(k)
    return out


TEMPLATES = "host string, pages long, container long, slot long, titles array<long>, dropped array<long>, constant array<long>, outline array<struct<label:string,depth:int>>"


def templates(pages: DataFrame) -> DataFrame:
    """One row for each host with a template: its number of distinct pages and the fields of ``Template``."""
    # Copies and url variants count once.
    once = _tokens(pages).groupBy("host", "page", "kind", "key", "up", "label", "article", "token").agg(*[F.max(c).alias(c) for c in ("n", "chars", "linked", "own", "place")])
    sums = [F.count(F.lit(1)).alias("pages"), F.bit_xor(F.xxhash64("n", "page")).alias("vector"), F.max("n").alias("most"), *[F.sum(c).alias(c) for c in ("chars", "linked", "own", "place")]]
    tokens = materialise(once.groupBy("host", "kind", "key", "up", "label", "article", "token").agg(*sums).where(F.col("pages") >= LEAST_PAGES), "tokens")
    hosts = tokens.where("kind = 'page'").select("host", F.col("pages").alias("all_pages"), F.col("vector").alias("root"))
    size = hosts.agg(F.sum(F.length("host") + 16)).first()[0] or 0
    # What is left of a host after this join is bounded by the length of its pages, not by their number; it is gathered with partial lists.
    frequent = tokens.where("kind <> 'page'").join(F.broadcast(hosts) if size <= BROADCAST_BYTES else hosts, "host").where(F.col("pages") >= LEAST_SHARE * F.col("all_pages"))
    row = F.struct("kind", "key", "up", "label", "article", "token", "pages", "vector", "most", "chars", "linked", "own", "place")
    gathered = frequent.groupBy("host", "all_pages", "root").agg(F.collect_list(row).alias("rows"))

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in batches:
            made = []
            for i in range(batch.num_rows):
                host, n, vector, rows = (batch.column(c)[i].as_py() for c in range(4))
                kinds = {kind: sorted((r for r in rows if r["kind"] == kind), key=lambda r: (r["place"] / r["pages"], r["key"], r["token"])) for kind in ("element", "order", "text")}
                found = deduce(n, vector, kinds["element"], kinds["order"], kinds["text"])
                if found:
                    made.append((host, n, *found[:-1], [{"label": x, "depth": d} for x, d in found.outline]))
            columns = list(zip(*made)) if made else [()] * len(OUT)
            yield pa.RecordBatch.from_arrays([pa.array(c, f.type) for c, f in zip(columns, OUT, strict=True)], schema=OUT)

    return materialise(gathered.mapInArrow(run, TEMPLATES), "templates")


_LONGS = pa.list_(pa.int64())
OUT = pa.schema(
    [("host", pa.string()), ("pages", pa.int64()), ("container", pa.int64()), ("slot", pa.int64()), ("titles", _LONGS), ("dropped", _LONGS), ("constant", _LONGS)]
    + [("outline", pa.list_(pa.struct([("label", pa.string()), ("depth", pa.int32())])))]
)


def main_text(source: str | None, container: int | None, slot: int | None, titles: list[int], dropped: list[int], constant: set[int]) -> str:
    """The article of one page, given its host's template if there is one (``container`` null: none)."""
    if not source:
        return ""
    page = Page(source)
    blocks = page.blocks()
    within = page.within({container}) if container is not None else []
    if not any(within[b.node] for b in blocks if within):
        within = page.within(page.own_article())
        return "\n".join(b.text for b in blocks if b.named and within[b.node])
    head, out = page.within(set(titles)), page.within(set(dropped))
    inside = [b for b in blocks if b.kept and (within[b.node] or head[b.node]) and not out[b.node]]
    rest = [b for b in inside if text_hash(b.text) not in constant] if constant else inside
    # Text that most pages repeat where the host's articles stand, with next to nothing beside it, is the article of near copies.
    emptied = any(page.key[b.node] == slot for b in inside) and not any(page.key[b.node] == slot for b in rest)
    mass, left = (sum(b.chars - b.linked for b in x) for x in (inside, rest))
    return "\n".join(b.text for b in (inside if emptied and left < LEAST_REST * mass else rest))


def extract(pages: DataFrame) -> DataFrame:
    """(page_id, url, text) of every page."""
    own = pages.select("page_id", "url", "html", host_of(F.col("url")).alias("host"))
    fields = ("container", "slot", "titles", "dropped", "constant")
    known = templates(own).select("host", *fields)
    size = known.agg(F.sum(F.length("host") + 8 * (F.size("constant") + F.size("titles") + F.size("dropped")) + 64)).first()[0] or 0
    joined = own.join(F.broadcast(known) if size <= BROADCAST_BYTES else known, "host", "left")
    schema = joined.select("page_id", "url").schema.add("text", "string", False)

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in batches:
            rows = zip(*(batch.column(i).to_pylist() for i in range(2, 8)), strict=True)
            made = [main_text(html, c, at, t or [], d or [], set(k or ())) for html, c, at, t, d, k in rows]
            yield pa.RecordBatch.from_arrays([batch.column(0), batch.column(1), pa.array(made, pa.string())], names=["page_id", "url", "text"])

    return joined.select("page_id", "url", "html", *fields).mapInArrow(run, schema)
