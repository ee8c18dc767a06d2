"""Main text of web pages by template deduction over the pages of a host.

A page is read as a sequence of tokens: every element that is not inline, told by its path (names, attributes and
places among like siblings), and every text block with the chain of elements around it. Tokens of one host that have
the same occurrence vector (how often each page has them) form an equivalence class. A class is valid when it is on
many pages and its tokens stand in one order on nearly all of them. Elements of valid classes make the template:
each class nests in the class of the element around its own, and what lies in an element of the template beside the
template's elements inside it are its slots. Every element's text is measured over all pages of the host: how much
there is, how much of it is linked, and whether it varies. The region of main text is found from the root of the
template by going into the one element that holds most of the text that varies and is not linked, as long as there is
one with more than a block. Its slots, but for linked ones, and a heading that was passed on the way are the text.

Names (article, nav, "comment") serve where the template cannot decide: on hosts of few pages, on hosts and pages
without such a region, and inside the region, where nothing else tells a reader's comment or a form from the text.

Vectors are never laid out: a token's vector is represented by sums over pages of 64-bit page hashes times
counts, so that a class is a group of equal sums and everything aggregates before it is shuffled.
"""

from __future__ import annotations

import html
import re
from collections.abc import Iterator
from decimal import Decimal
from functools import lru_cache

import pandas as pd
import pyarrow as pa
import xxhash
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from channelalign.llm.memory import released
from channelalign.llm.store import written

#: A class must be on this many pages of its host, and on this share of them, to be template.
LEAST_PAGES, LEAST_SHARE = 8, 0.8
#: Slots with a larger share of linked words are menus.
LINKED = 0.5
#: The share of an element's text that one element inside it must hold to be gone into, and the blocks it must have on average.
DOMINANT, BLOCKS = 0.7, 1.5
#: Rows of template facts that are sent to every executor; beyond it they are joined to the pages by host.
SENT_ROWS = 200_000
#: Parts over which a host's pages are dealt when its classes are joined to them.
SALTS = 16

# Element names by role, and words in class, id or role attributes of boilerplate.
VOID = frozenset("area base br col embed hr img input link meta param source track wbr".split())
RAW = frozenset("script style noscript template iframe textarea title svg math object select".split())
INLINE = frozenset("a abbr acronym b bdi bdo big cite code data del dfn em font i ins kbd label mark q s samp small span strike strong sub sup time tt u var br img wbr".split())
ASIDE = frozenset("nav footer aside form button dialog menu".split())
CLOSES_ITSELF = {"p": {"p"}, "li": {"li"}, "dt": {"dt", "dd"}, "dd": {"dt", "dd"}, "tr": {"tr", "td", "th"}, "td": {"td", "th"}, "th": {"td", "th"}, "option": {"option"}}
SCOPES = frozenset("ul ol table td th article section div aside nav header footer main form body blockquote dl".split())
BOILERPLATE_WORDS = frozenset(
    "ad ads advert adverts advertisement advertising sponsor sponsored promo promotion banner cookie cookies consent gdpr notice notices alert newsletter subscribe subscription popup modal overlay "
    "sidebar aside widget menu nav navbar navigation breadcrumb breadcrumbs footer masthead comment comments respond disqus reply replies related recommended recommendations share sharing social "
    "toolbar pagination pager login signin signup search skip copyright legal disclaimer complementary contentinfo dialog form".split()
)
HEADER_WORDS = frozenset("header banner topbar".split())
MAIN_ELEMENTS = frozenset(["article", "main"])

_TAG = re.compile(r"<!--.*?(?:-->|\Z)|<[!?][^>]*(?:>|\Z)|<(/?)([a-zA-Z][^\s/>]*)((?:[^>\"']|\"[^\"]*\"|'[^']*')*+)>", re.S)
_ATTRIBUTE = re.compile(r"\b(class|id|role)\s*=\s*(?:\"([^\"]*)\"|'([^']*)'|([^\s>]+))", re.I)
_HIDDEN = re.compile(r"\bhidden\b|display\s*:\s*none", re.I)
_UNFINISHED = re.compile(r"<(?:/?[a-zA-Z]|[!?])[^<]*\Z")
_SPACE = re.compile(r"\s+")
_HOST = re.compile(r"^[a-zA-Z][a-zA-Z0-9+.-]*://(?:[^/?#@]*@)?([^/?#:]*)")


def host_of(url: str | None) -> str:
    m = _HOST.match(url or "")
    return m[1].lower() if m else ""


@lru_cache(maxsize=1 << 14)
def _element(name: str, attributes: str) -> tuple[str, bool, bool]:
    """(label of the element, whether it is boilerplate anywhere, whether it is a page header)."""
    words = [(w or x or y).lower() for _, w, x, y in _ATTRIBUTE.findall(attributes)]
    parts = {p for w in words for p in re.split(r"[^a-z]+", w)}
    label = ".".join([name, *sorted(re.sub(r"\d+", "0", w) for w in words if w)])
    return label, name in ASIDE or bool(parts & BOILERPLATE_WORDS) or bool(_HIDDEN.search(attributes)), name == "header" or bool(parts & HEADER_WORDS)


class _Open:
    """An element whose end has not come."""

    __slots__ = ("aside", "blocks", "chain", "header", "linked", "main", "name", "print", "region", "seen", "token", "words")

    def __init__(self, name: str = "", chain: str = "", token: int = 0, aside: bool = False, header: bool = False, main: bool = False, region: bool = False, seen: dict | None = None):
        self.name, self.chain, self.token, self.aside, self.header, self.main, self.region = name, chain, token, aside, header, main, region
        self.seen: dict[str, int] = {} if seen is None else seen
        self.words = self.linked = self.blocks = self.print = 0


class Page:
    """Text blocks and elements of one page, in page order. region, titles, menus: tokens of elements by which the host's template decides."""

    __slots__ = ("blocks", "nodes", "places")

    def __init__(self, source: str, region: int | None = None, titles: frozenset[int] = frozenset(), menus: frozenset[int] = frozenset()):
        #: (text, chain, boilerplate, inside a main element, words, linked words, inside the region)
        self.blocks: list[tuple[str, str, bool, bool, int, int, bool]] = []
        #: (token, token around it, name, words, linked words, blocks, hash of the text)
        self.nodes: list[tuple[int, int, str, int, int, int, int]] = []
        #: tokens of elements and of text outside main elements
        self.places: list[int] = []
        top = _Open()
        stack: list[_Open] = []
        parts: list[str] = []
        linked, links, at = 0, 0, 0

        def around(n: int) -> _Open:
            return next((s for s in reversed(stack[:n]) if s.name not in INLINE), top)

        def flush() -> None:
            nonlocal linked
            text = _SPACE.sub(" ", html.unescape("".join(parts))).strip()
            parts.clear()
            if text:
                inner = around(len(stack))
                n = text.count(" ") + 1
                self.blocks.append((text, inner.chain, inner.aside or (inner.header and not inner.main), inner.main, n, min(linked, n), inner.region))
                inner.words += n
                inner.linked += min(linked, n)
                inner.blocks += 1
                inner.print += _token(text)
                if not inner.main:
                    self.places.append(_token(f"{inner.chain}\0{text}"))
            linked = 0

        def take(piece: str) -> None:
            nonlocal linked
            if piece:
                parts.append(piece)
                if links:
                    linked += len(piece.split())

        def pop(n: int) -> None:
            nonlocal links
            while len(stack) > n:
                s = stack.pop()
                links -= s.name == "a"
                if s.name not in INLINE:
                    outer = around(len(stack))
                    self.nodes.append((s.token, outer.token, s.name, s.words, s.linked, s.blocks, s.print % (1 << 64) - (1 << 63)))
                    outer.words += s.words
                    outer.linked += s.linked
                    outer.blocks += s.blocks
                    outer.print += s.print

        while True:
            m = _TAG.search(source, at)
            if m is None:
                rest = source[at:]
                if u := _UNFINISHED.search(rest):
                    rest = rest[: u.start()]
                take(rest)
                break
            take(source[at : m.start()])
            at = m.end()
            if not m[2]:
                continue
            name = m[2].lower()
            if m[1]:
                place = next((i for i in range(len(stack) - 1, -1, -1) if stack[i].name == name), None)
                if name not in INLINE:
                    flush()
                if place is not None:
                    pop(place)
                continue
            if name not in INLINE:
                flush()
                closing = CLOSES_ITSELF.get(name, {"p"} if name not in VOID else ())
                for i in range(len(stack) - 1, -1, -1):
                    if stack[i].name in closing:
                        pop(i)
                        break
                    if stack[i].name in SCOPES:
                        break
            elif name in ("br", "wbr", "img"):
                parts.append(" " if name != "wbr" else "")
            if name in RAW:
                close = re.compile(rf"</{name}\b[^>]*>", re.I).search(source, at)
                at = close.end() if close else len(source)
                continue
            if name in VOID or m[3].endswith("/"):
                continue
            label, aside, header = _element(name, m[3])
            above = stack[-1] if stack else top
            links += name == "a"
            if name in INLINE:
                stack.append(_Open(name, above.chain, above.token, above.aside or aside, above.header or (header and not above.main), above.main, above.region, above.seen))
                continue
            place = above.seen[label] = above.seen.get(label, 0) + 1
            token = _token(f"{above.token}/{label}[{place}]")
            self.places.append(token)
            if token == region or token in titles:  # what the template says goes before names around it
                stack.append(_Open(name, f"{above.chain}/{label}", token, main=True, region=True))
                continue
            main = above.main or (name in MAIN_ELEMENTS and not aside and not above.aside)
            stack.append(_Open(name, f"{above.chain}/{label}", token, above.aside or aside or (above.region and token in menus), (above.header or header) and not main, main, above.region))
        flush()
        pop(0)

    def text(self, constant: frozenset[int] = frozenset(), menus: frozenset[int] = frozenset()) -> str:
        """The blocks of the main slots: of the region, where the page has it; else by names. constant: hashes of (chain, text) that are template, outside of main elements; menus: hashes of chains of linked slots."""
        chosen = [b for b in self.blocks if b[6] and not b[2]]
        if not chosen:
            usable = [b for b in self.blocks if not b[2]]
            inside = [b for b in usable if b[3]]
            chosen = inside or [b for b in usable if _token(f"{b[1]}\0{b[0]}") not in constant and _token(b[1]) not in menus and b[5] <= LINKED * b[4]]
        return "\n".join(b[0] for b in chosen)


def _token(name: str) -> int:
    return xxhash.xxh64_intdigest(name.encode("utf-8", "replace")) - (1 << 63)


def _pages(batches: Iterator[pa.RecordBatch]) -> Iterator[tuple[pa.RecordBatch, int, str, Page, int]]:
    for batch in batches:
        for n, (url, source) in enumerate(zip(batch.column("url").to_pylist(), batch.column("html"), strict=True)):
            key = _token(f"{url}\0{n}\0{batch.column('page_id')[n].as_py()}")
            yield batch, n, host_of(url), Page(source.as_py() or ""), key


TOKENS = "host string, token long, kind string, around long, name string, pages long, vector long, words long, linked long, blocks long, low long, high long"


def _tokens(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
    """Sums over pages of each host's tokens: kind node (an element by its path), text (a block) or slot (a chain that holds text)."""
    held: dict[tuple[str, int, str], list] = {}
    kinds = [pa.string(), pa.int64(), pa.string(), pa.int64(), pa.string(), *[pa.int64()] * 7]
    names = ["host", "token", "kind", "around", "name", "pages", "vector", "words", "linked", "blocks", "low", "high"]

    def out() -> pa.RecordBatch:
        columns = [[k[n] for k in held] for n in range(3)] + [[v[n] for v in held.values()] for n in range(9)]
        held.clear()
        return pa.RecordBatch.from_arrays([pa.array(c, k) for c, k in zip(columns, kinds, strict=True)], names=names)

    def add(name: tuple[str, int, str], key: int, count: int, words: int = 0, linked: int = 0, blocks: int = 0, print_: int = 0, around: int = 0, label: str = "") -> None:
        sums = held.get(name)
        if sums is None:
            held[name] = [around, label, 1, _signed(key * count), words, linked, blocks, print_, print_]
            return
        sums[2] += 1
        sums[3] = _signed(sums[3] + key * count)
        sums[4] += words
        sums[5] += linked
        sums[6] += blocks
        sums[7], sums[8] = min(sums[7], print_), max(sums[8], print_)

    for _, _, host, page, key in _pages(batches):
        for token, around, name, words, linked, blocks, print_ in page.nodes:
            add((host, token, "node"), key, 1, words, linked, blocks, print_, around, name)
        counts: dict[tuple[int, str], list[int]] = {}
        for text, chain, aside, main, n, linked, _ in page.blocks:
            if aside or main:
                continue  # left out, or kept, whatever the template says of this text
            counts.setdefault((_token(f"{chain}\0{text}"), "text"), [0, 0, 0])[0] += 1
            slot = counts.setdefault((_token(chain), "slot"), [0, 0, 0])
            slot[0] += 1
            slot[1] += n
            slot[2] += linked
        for (token, kind), (count, words, linked) in counts.items():
            add((host, token, kind), key, count, words, linked)
        add((host, 0, "pages"), 0, 0)
        if len(held) > 100_000:
            yield out()
    yield out()


def _signed(x: int) -> int:
    return (x + (1 << 63)) % (1 << 64) - (1 << 63)


def classes_of(pages: DataFrame) -> DataFrame:
    """Tokens in equivalence classes that are frequent enough, with class, class_size and their sums. pages: page_id, url, html."""
    sums = written(
        pages.mapInArrow(released(_tokens), TOKENS).groupBy("host", "token", "kind").agg(
            # sums of 64-bit values modulo 2**64, by way of decimals that cannot overflow
            F.max("around").alias("around"), F.max("name").alias("name"), F.sum("pages").alias("pages"), F.sum(F.col("vector").cast("decimal(38,0)")).alias("vector"),
            F.sum("words").alias("words"), F.sum("linked").alias("linked"), F.sum("blocks").alias("blocks"), F.min("low").alias("low"), F.max("high").alias("high"),
        ), "tokens"
    )
    wrapped = F.pmod(F.col("vector"), F.lit(Decimal(2**64)))
    totals = sums.where("kind = 'pages'").select("host", F.col("pages").alias("host_pages"))
    frequent = sums.where("kind <> 'pages'").join(totals, "host").where((F.col("pages") >= LEAST_PAGES) & (F.col("pages") >= LEAST_SHARE * F.col("host_pages"))).withColumn("vector", wrapped)
    groups = frequent.where("kind <> 'slot'").groupBy("host", "vector").agg(F.count(F.lit(1)).alias("class_size"))
    members = frequent.join(groups.select("host", F.col("vector").alias("_v"), "class_size"), (F.col("vector") == F.col("_v")) & (frequent["host"] == groups["host"]), "left").drop(groups["host"])
    return members.select("host", "token", "kind", "around", "name", F.coalesce("class_size", F.lit(0)).alias("class_size"), F.xxhash64(F.col("vector").cast("string")).alias("class"), "pages", "host_pages", "words", "linked", "blocks", "low", "high")


def _places(page: Page) -> list[int]:
    """The page's distinct tokens in the order of their first places."""
    return list(dict.fromkeys(page.places))


def _orders(facts: dict[str, dict[int, int]]):
    """For each class, the hash of the order of the first places of its tokens on a page, and on how many pages it is that."""

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        held: dict[tuple[str, int, int], int] = {}
        for _, _, host, page, _ in _pages(batches):
            wanted = facts.get(host)
            if not wanted:
                continue
            order: dict[int, list[int]] = {}
            for token in _places(page):
                if token in wanted:
                    order.setdefault(wanted[token], []).append(token)
            for name, tokens in order.items():
                key = (host, name, _token(",".join(map(str, tokens))))
                held[key] = held.get(key, 0) + 1
        keys = list(held)
        yield pa.RecordBatch.from_arrays([pa.array([k[0] for k in keys], pa.string()), pa.array([k[1] for k in keys], pa.int64()), pa.array([k[2] for k in keys], pa.int64()), pa.array([held[k] for k in keys], pa.int64())], names=["host", "class", "order", "pages"])

    return run


def _placed(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
    """host, page, token, place of every distinct token of every page."""
    columns: list[list] = [[], [], [], []]

    def out() -> pa.RecordBatch:
        kinds = [pa.string(), pa.int64(), pa.int64(), pa.int32()]
        batch = pa.RecordBatch.from_arrays([pa.array(c, k) for c, k in zip(columns, kinds, strict=True)], names=["host", "page", "token", "place"])
        for c in columns:
            c.clear()
        return batch

    for batch, n, host, page, _ in _pages(batches):
        tokens = _places(page)
        for c, values in zip(columns, ([host] * len(tokens), [batch.column("_row")[n].as_py()] * len(tokens), tokens, range(len(tokens))), strict=True):
            c.extend(values)
        if len(columns[0]) > 100_000:
            yield out()
    yield out()


def _joined_orders(pages: DataFrame, members: DataFrame) -> DataFrame:
    """The same as _orders() for members (host, token, class) of any number: they meet the pages' tokens in a shuffle. A host's pages are dealt over SALTS parts."""
    salt = lambda row: F.pmod(row, F.lit(SALTS)).cast("int")
    placed = pages.withColumn("_row", F.monotonically_increasing_id()).mapInArrow(released(_placed), "host string, page long, token long, place int").withColumn("salt", salt(F.col("page")))
    spread = members.withColumn("salt", F.explode(F.sequence(F.lit(0), F.lit(SALTS - 1))))
    order = placed.join(spread, ["host", "token", "salt"]).groupBy("host", "class", "page").agg(F.array_sort(F.collect_list(F.struct("place", "token"))).alias("order"))
    return order.select("host", "class", F.xxhash64(F.transform("order", lambda x: x["token"])).alias("order"), F.lit(1).cast("long").alias("pages"))


def main_region(nodes: list[dict]) -> tuple[int | None, list[int], list[int]]:
    """(token of the region or None, tokens of headings passed on the way, tokens of linked elements inside the region) of one host's template.

    nodes: token, around, name, words, linked, blocks, pages, low, high (least and largest hash of the text) of the
    elements of valid classes. An element nests in the nearest element around it that is in the template, too.
    """
    by = {n["token"]: n for n in nodes}
    inside: dict[int, list[int]] = {}
    for n in nodes:
        inside.setdefault(n["around"] if n["around"] in by else 0, []).append(n["token"])

    def below(token: int) -> Iterator[int]:
        todo = list(inside.get(token, ()))
        while todo:
            t = todo.pop()
            yield t
            todo += inside.get(t, ())

    def still(n: dict) -> bool:
        return n["low"] == n["high"]

    def varying(token: int) -> int:
        """Words that are not linked, without those of elements whose text is the same on all pages."""
        total, todo = 0, [(token, 1)]
        while todo:
            t, sign = todo.pop()
            n = by[t]
            if still(n):
                total += 0 if sign > 0 else n["linked"] - n["words"]
                continue
            if sign > 0:
                total += n["words"] - n["linked"]
            todo += [(c, -1) for c in inside.get(t, ())]
        return max(0, total)

    region, titles = 0, []
    amount = sum(varying(t) for t in inside.get(0, ()))
    while amount and not (region and by[region]["name"] in MAIN_ELEMENTS):
        held = {t: varying(t) for t in inside.get(region, ())}
        best = max(held, key=lambda t: (held[t], -t), default=None)
        if best is None or held[best] < DOMINANT * amount or by[best]["blocks"] < BLOCKS * by[best]["pages"]:
            break
        passed = [t for c in held if c != best for t in (c, *below(c))]
        titles += [t for t in passed if by[t]["name"] == "h1" and not still(by[t]) and by[t]["linked"] <= LINKED * by[t]["words"]]
        region, amount = best, held[best]
    if not region or by[region]["name"] in ("html", "body"):
        return None, [], []
    return region, sorted(titles), sorted(t for t in below(region) if by[t]["linked"] > LINKED * by[t]["words"])


def templates(pages: DataFrame) -> DataFrame:
    """(host, constant, menus, region, titles): what the template of a host says; hosts without anything are left out.

    A class is valid if one order of its tokens is on LEAST_SHARE of its pages; a text block is template if its
    class is valid and has two or more tokens. Slots outside of main elements count as menus by their share of
    linked words over the whole host. region, titles and elements among the menus come from main_region(). A host's
    elements of valid classes come together in one task: each is on most pages, so they are hardly more than one
    page holds.
    """
    facts = written(classes_of(pages), "classes")
    members = facts.where("kind <> 'slot' AND class_size > 1").select("host", "token", "class")
    rows = members.limit(SENT_ROWS + 1).collect()
    if len(rows) <= SENT_ROWS:
        by_host: dict[str, dict[int, int]] = {}
        for r in rows:
            by_host.setdefault(r["host"], {})[r["token"]] = r["class"]
        order = pages.mapInArrow(released(_orders(by_host)), "host string, class long, order long, pages long")
    else:
        order = _joined_orders(pages, members)
    counted = order.groupBy("host", "class", "order").agg(F.sum("pages").alias("pages")).groupBy("host", "class").agg(F.max("pages").alias("most"), F.sum("pages").alias("all"))
    valid = counted.where(F.col("most") >= LEAST_SHARE * F.col("all")).select("host", "class")
    good = written(facts.where("kind <> 'slot' AND class_size > 1").join(valid, ["host", "class"], "left_semi"), "valid")
    menus = facts.where((F.col("kind") == "slot") & (F.col("linked") > LINKED * F.col("words")))

    def decide(group: pd.DataFrame) -> pd.DataFrame:
        region, titles, linked = main_region(group.to_dict("records"))
        return pd.DataFrame({"host": [group["host"].iloc[0]], "region": pd.array([region], "Int64"), "titles": [titles], "linked": [linked]})

    nodes = good.where("kind = 'node'").select("host", "token", "around", "name", "words", "linked", "blocks", "pages", "low", "high")
    regions = nodes.groupBy("host").applyInPandas(decide, "host string, region long, titles array<long>, linked array<long>").where("region IS NOT NULL")
    none = F.array().cast("array<long>")
    marked = good.where("kind = 'text'").select("host", "token", F.lit("text").alias("kind")).unionByName(menus.select("host", "token", F.lit("slot").alias("kind")))
    marked = marked.groupBy("host").agg(F.collect_list(F.when(F.col("kind") == "text", F.col("token"))).alias("constant"), F.collect_list(F.when(F.col("kind") == "slot", F.col("token"))).alias("menus"))
    return marked.join(regions, "host", "full").select("host", F.coalesce("constant", none).alias("constant"), F.concat(F.coalesce("menus", none), F.coalesce("linked", none)).alias("menus"), "region", F.coalesce("titles", none).alias("titles"))


def _ready(fact: tuple) -> tuple[frozenset[int], frozenset[int], int | None, frozenset[int]]:
    return frozenset(fact[0] or ()), frozenset(fact[1] or ()), fact[2], frozenset(fact[3] or ())


def extract_text(pages: DataFrame, id_col: str = "page_id", url_col: str = "url", html_col: str = "html") -> DataFrame:
    """One row per page: page_id, url, text, n_chars (code points).

    Null html is empty and gives an empty text; pages without a usable url share the empty host. A host with few
    pages has no template; its pages are read by their elements alone. Character references are decoded, white
    space inside a block becomes one space, blocks are joined by a newline; nothing else is dropped or capped.
    Rows that repeat a page_id are pages each; an empty table gives no rows; a page of any size is read as a whole.
    """
    own = pages.select(F.col(id_col).cast("long").alias("page_id"), F.col(url_col).alias("url"), F.coalesce(F.col(html_col), F.lit("")).alias("html"))
    facts = written(templates(own), "templates")
    n = facts.agg(F.sum(F.size("constant") + F.size("menus") + F.size("titles")), F.count(F.lit(1))).first()

    def read(batches: Iterator[pa.RecordBatch], known: dict | None) -> Iterator[pa.RecordBatch]:
        names = ("constant", "menus", "region", "titles")
        for batch in batches:
            for first in range(0, batch.num_rows, 256):
                part = batch.slice(first, 256)
                texts = []
                given = zip(*[part.column(c).to_pylist() for c in names], strict=True) if known is None else None
                for url, source in zip(part.column("url").to_pylist(), part.column("html"), strict=True):
                    constant, menus, region, titles = _ready(next(given)) if given is not None else known.get(host_of(url), _ready((None, None, None, None)))
                    texts.append(Page(source.as_py(), region, titles, menus).text(constant, menus))
                yield pa.RecordBatch.from_arrays([part.column("page_id"), part.column("url"), pa.array(texts, pa.string()), pa.array(list(map(len, texts)), pa.int64())], names=["page_id", "url", "text", "n_chars"])

    schema = "page_id long, url string, text string, n_chars long"
    if (n[0] or 0) + n[1] <= SENT_ROWS:  # checked: so many numbers at most go to every executor
        known = {r["host"]: _ready((r["constant"], r["menus"], r["region"], r["titles"])) for r in facts.collect()}
        return own.mapInArrow(released(lambda batches: read(batches, known)), schema)
    host = F.lower(F.regexp_extract(F.coalesce("url", F.lit("")), r"^[a-zA-Z][a-zA-Z0-9+.-]*://(?:[^/?#@]*@)?([^/?#:]*)", 1))
    return own.join(facts, host == facts["host"], "left").drop("host").mapInArrow(released(lambda batches: read(batches, None)), schema)
