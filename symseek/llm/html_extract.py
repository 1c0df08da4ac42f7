"""Main-text extraction from web pages by differencing each page with its nearest neighbours by URL.

A page is cut into lines (blocks of text). Its neighbours are the pages before and after it in the order of
(host, path), so no page of the host shares a longer start of the path. The lines of a page and of each neighbour are
aligned by a longest common subsequence, and the shared lines, a template's, go.

What makes two lines equal is their slot, the path of elements with their classes and ids, and their text. Menus, adverts and footers keep
their slot from page to page while their words change, so a line that markup tells from content is compared by its slot alone: all lines outside of the main content,
where a page marks one (article, main and the like), and lines in a suspicious element (a class like `ad`). The main content itself is protected: articles quote
each other's sentences, so equal texts don't make a template there. A page that marks no main content has all its lines compared, by slot and text.

What differencing can't tell, because no neighbour has it, markup decides: lines outside of the marked main content and lines in menus, headers, footers,
sidebars, forms and dialogs go, by their tag or role. A suspicious class never decides alone: its lines stay if neighbours were asked and none has the slot.

Only narrow rows are sorted and joined: line hashes, no texts. The order is a range partitioning with a global rank, so a
host with a third of all pages spreads over many tasks.

Defined results: null or empty html gives an empty text; null URLs have no neighbours, and suspicious lines of such a page go; pages with equal URLs are
each other's neighbours; where no main content is marked, equal pages don't erase each other; equal rows (key, URL and html) are one page to the order; an unclosed element
ends with its parent or the page; a tag cut off at the end of the page is dropped. Pages of many equal lines are aligned in bounded memory.
"""

from __future__ import annotations

import html as entities
import re
from bisect import bisect_left
from typing import NamedTuple

import numpy as np
import pyarrow as pa
import xxhash
from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

from symseek.llm.common import column_of, list_array, map_texts, records, written

# What HTML elements are for.
_RAW = "script|style|template|textarea|select|title"
_INLINE = frozenset(
    "a abbr acronym b bdi bdo big cite code data del dfn em font i img input ins kbd label mark meter output q rp rt ruby s samp small span strike strong sub sup time tt u var wbr "
    "audio canvas iframe map noscript object picture svg video text tspan textpath g path math mi mn mo ms mtext mrow mfrac msqrt mroot mstyle merror mpadded mphantom msub msup msubsup munder mover munderover semantics annotation".split()
)
_VOID = frozenset("area base br col embed hr img input link meta param source track wbr".split())
_ENDED_BY_NEXT = {"li": frozenset(("li",)), "dt": frozenset(("dt", "dd")), "dd": frozenset(("dt", "dd")), "tr": frozenset(("tr", "td", "th")), "td": frozenset(("td", "th")), "th": frozenset(("td", "th")), "option": frozenset(("option",))}
_BOILERPLATE_TAGS = frozenset("nav header footer aside form head button dialog menu".split())
_MAIN_TAGS = frozenset(("article", "main"))
_SUSPICIOUS_WORDS = frozenset(
    "ad ads advert advertisement advertising adsense sponsored cookie-notice cookie-banner cookie-consent consent-banner newsletter sidebar navbar breadcrumb breadcrumbs pagination "
    "comment comments comment-list commentlist share-buttons social-share".split()
)
_BOILERPLATE_ROLES = frozenset("navigation banner contentinfo complementary search form menu menubar dialog alert alertdialog toolbar".split())
_MAIN_WORDS = frozenset("articlebody article-body article_body article-content post-content post-body entry-content main-content maincontent story-body".split())
_TOKEN = re.compile(
    rf"<!--.*?(?:-->|\Z)|<(?P<raw>{_RAW})\b(?:[^>\"']|\"[^\"]*\"|'[^']*')*>.*?(?:</(?P=raw)\s*>|\Z)|<[!?][^>]*(?:>|\Z)"
    r"|<(?P<close>/?)(?P<name>[a-zA-Z][^\s/>]*)(?P<attributes>(?:[^>\"']|\"[^\"]*\"|'[^']*')*)>|</?[a-zA-Z][^>]*(?:>|\Z)",
    re.IGNORECASE | re.DOTALL,
)
_ATTRIBUTE = re.compile(r"""\b(class|id|role|itemprop)\b\s*=\s*("[^"]*"|'[^']*'|[^\s>]+)""", re.IGNORECASE)
#: Pairs of equal lines up to which two pages are aligned pair by pair.
PAIRS = 1 << 20


class Line(NamedTuple):
    """A block of text, and what the markup says of it."""

    text: str
    main: bool  # inside marked main content, and in nothing that ends it
    off: bool  # a menu, footer and the like by its tag or role
    suspicious: bool  # by a class or id
    slot: int  # the path of elements with their classes and ids


class _Open(NamedTuple):
    name: str
    main: bool
    off: bool
    suspicious: bool
    slot: int


def _bearing(name: str, attributes: str) -> tuple[bool, bool, bool, str]:
    """What an element's own tag and attributes say: main content, boilerplate, suspicious; and its classes and id."""
    main, off, suspicious, names = name in _MAIN_TAGS, name in _BOILERPLATE_TAGS, False, ""
    for kind, value in _ATTRIBUTE.findall(attributes) if attributes else ():
        kind, value = kind.lower(), value.strip("\"'").lower()
        if kind == "role":
            main, off = main or value == "main", off or value in _BOILERPLATE_ROLES
        elif kind == "itemprop":
            main = main or value == "articlebody"
        else:
            own = value.split()
            main = main or not _MAIN_WORDS.isdisjoint(own)
            suspicious = suspicious or not _SUSPICIOUS_WORDS.isdisjoint(own)
            if kind == "class":
                names = f"{names}.{value}"
    return main, off, suspicious, names


def _hash(text: str, seed: int = 0) -> int:
    return xxhash.xxh3_64_intdigest(text.encode("utf-8", "surrogatepass"), seed) - (1 << 63)


def lines_of(page: str | None) -> list[Line]:
    """A page's blocks of text in order."""
    out: list[Line] = []
    parts: list[str] = []
    stack = [_Open("", False, False, False, 0)]
    names: dict[str, int] = {}  # how often an element is on the stack

    def flush() -> None:
        if parts:
            text = " ".join(entities.unescape("".join(parts)).split())
            if text:
                out.append(Line(text, *stack[-1][1:]))
            parts.clear()

    def end() -> None:
        names[stack.pop().name] -= 1

    page, at = page or "", 0
    for token in _TOKEN.finditer(page):
        if token.start() > at:
            parts.append(page[at : token.start()])
        at = token.end()
        name = token["name"]
        if name is None:
            continue
        name = name.lower()
        if name == "br":
            parts.append(" ")
        elif token["close"]:
            if name not in _INLINE or names.get(name):
                flush()
            if names.get(name):
                while stack[-1].name != name:
                    end()
                end()
        else:
            attributes = token["attributes"]
            main, off, suspicious, classes = _bearing(name, attributes) if attributes.strip() or name in _BOILERPLATE_TAGS or name in _MAIN_TAGS else (False, False, False, "")
            tells = main or off or suspicious
            if name not in _INLINE or tells:
                flush()
                if name not in _INLINE and stack[-1].name == "p":
                    end()
                ended = _ENDED_BY_NEXT.get(name, ())
                while stack[-1].name in ended:
                    end()
            if name not in _VOID and not attributes.endswith("/") and (name not in _INLINE or tells or names.get(name)):
                over = stack[-1]
                # Main content inside boilerplate counts if none is open yet: some pages are one form.
                inside = over.main if not main else over.main or not over.off or not (names.get("article") or names.get("main"))
                stack.append(_Open(name, inside and not off, over.off and not (main and inside) or off, over.suspicious or suspicious, _hash(name + classes, over.slot & (1 << 64) - 1)))
                names[name] = names.get(name, 0) + 1
    parts.append(page[at:])
    flush()
    return out


def _by_pairs(own: list[int], other: list[int], where: dict[int, list[int]]) -> list[int]:
    tails: list[int] = []  # the smallest last position of a common subsequence of each length
    ends: list[int] = []
    chain: list[tuple[int, int]] = []  # (position in own, previous link)
    for i, x in enumerate(own):
        for j in reversed(where.get(x, ())):
            k = bisect_left(tails, j)
            chain.append((i, ends[k - 1] if k else -1))
            if k == len(tails):
                tails.append(j)
                ends.append(len(chain) - 1)
            else:
                tails[k], ends[k] = j, len(chain) - 1
    found, link = [], ends[-1] if ends else -1
    while link >= 0:
        i, link = chain[link]
        found.append(i)
    return found


def _lengths(own: list[int], other: list[int]) -> np.ndarray:
    """Lengths of the longest common subsequences of own and other[:j] for all j, with a bit for each line of other."""
    where: dict[int, list[int]] = {}
    for j, x in enumerate(other):
        where.setdefault(x, []).append(j)
    size, masks = len(other), {}
    full = (1 << size) - 1
    row = full
    for x in own:
        places = where.get(x)
        if not places:
            continue
        mask = masks.get(x)
        if mask is None:
            bits = np.zeros(size, np.uint8)
            bits[places] = 1
            mask = int.from_bytes(np.packbits(bits, bitorder="little").tobytes(), "little")
            if len(masks) < 256:
                masks[x] = mask
        met = row & mask
        row = (row + met | row - met) & full
    bits = np.unpackbits(np.frombuffer(row.to_bytes(size // 8 + 1, "little"), np.uint8), bitorder="little")[:size]
    return np.concatenate([[0], np.cumsum(1 - bits.astype(np.int64))])


def shared_lines(own: list[int], other: list[int]) -> set[int]:
    """Positions in `own` that a longest common subsequence with `other` uses. Memory grows with the lines and PAIRS, not with the pairs of equal lines."""
    found: set[int] = set()
    rest = [(0, list(own), list(other))]
    while rest:
        base, a, b = rest.pop()
        head = next((i for i, (x, y) in enumerate(zip(a, b, strict=False)) if x != y), min(len(a), len(b)))
        found.update(range(base, base + head))
        a, b = a[head:], b[head:]
        tail = next((i for i, (x, y) in enumerate(zip(reversed(a), reversed(b), strict=False)) if x != y), min(len(a), len(b)))
        found.update(range(base + head + len(a) - tail, base + head + len(a)))
        a, b, base = a[: len(a) - tail], b[: len(b) - tail], base + head
        where: dict[int, list[int]] = {}
        for j, y in enumerate(b):
            where.setdefault(y, []).append(j)
        if sum(len(where.get(x, ())) for x in a) <= PAIRS or len(a) < 2:
            found.update(base + i for i in _by_pairs(a, b, where)) if len(a) > 1 else found.update(base + i for i, x in enumerate(a) if x in where)
            continue
        middle = len(a) // 2
        upper, lower = _lengths(a[:middle], b), _lengths(a[middle:][::-1], b[::-1])[::-1]
        cut = int(np.argmax(upper + lower))
        rest += [(base, a[:middle], b[:cut]), (base + middle, a[middle:], b[cut:])]
    return found


class Offer(NamedTuple):
    """What a page offers for comparison: its unprotected lines."""

    slots: list[int]
    fulls: list[int]  # slot and text
    firm: list[bool]  # compared by slot alone, whoever asks


def offered(lines: list[Line]) -> tuple[list[int], Offer]:
    """Which lines are unprotected, and what they offer."""
    marked = any(x.main and not x.suspicious for x in lines)
    at = [i for i, x in enumerate(lines) if not (marked and x.main and not x.suspicious)]
    return at, Offer([lines[i].slot for i in at], [_hash(lines[i].text, lines[i].slot & (1 << 64) - 1) for i in at], [lines[i].off or lines[i].suspicious for i in at])


def main_text(lines: list[Line], around: list[Offer] | None) -> tuple[str, int, int]:
    """The text left of a page, and how many lines differencing and markup took. around: what its neighbours offer; None or empty if there are none."""
    marked = any(x.main and not x.suspicious for x in lines)
    at, own = offered(lines)
    ids = lambda offer: offer.slots if marked else [s if f else t for s, t, f in zip(*offer, strict=True)]
    mine, gone = ids(own), set()
    others = [x for x in around or () if marked or x.fulls != own.fulls]  # a copy of a page says nothing about a template
    for other in others:
        gone |= shared_lines(mine, ids(other))
    differenced = {at[i] for i in gone}
    by_markup = {i for i, x in enumerate(lines) if i not in differenced and ((marked and not x.main) or x.off or (x.suspicious and not others))}
    return "\n".join(x.text for i, x in enumerate(lines) if i not in differenced and i not in by_markup), len(differenced), len(by_markup)


def url_host(url: Column) -> Column:
    return F.lower(F.regexp_extract(url, r"^[A-Za-z][A-Za-z0-9+.-]*://([^/?#]*)", 1))


def url_path(url: Column) -> Column:
    return F.regexp_extract(url, r"^[A-Za-z][A-Za-z0-9+.-]*://[^/?#]*([^?#]*)", 1)


def neighbours(df: DataFrame, *, key: str = "page_id", url: str = "url", html: str = "html", near: int = 2) -> DataFrame:
    """row (a hash of key, URL and html), and `around`: what the `near` pages before and after it on its host offer."""
    rows = df.where(F.col(url).isNotNull()).select(F.xxhash64(F.col(key), F.col(url), F.col(html)).alias("row"), url_host(F.col(url)).alias("host"), url_path(F.col(url)).alias("path"), F.col(html).alias("body"))

    def step(batch: pa.RecordBatch) -> pa.RecordBatch:
        offers = [offered(lines_of(x))[1] for x in column_of(batch, "body").to_pylist()]
        counts = np.array([len(x.slots) for x in offers])
        flat = [pa.array([v for x in offers for v in x[c]], kind) for c, kind in enumerate((pa.int64(), pa.int64(), pa.bool_()))]
        return records(row=column_of(batch, "row"), host=column_of(batch, "host"), path=column_of(batch, "path"), **{c: list_array(v, counts) for c, v in zip(Offer._fields, flat, strict=True)})

    narrow = written(map_texts(rows, step, "row long, host string, path string, slots array<long>, fulls array<long>, firm array<boolean>", text="body"), "page-lines").dropDuplicates(["row"])
    # The number is (partition, row in it) of the sorted order; the written table fixes it, and each partition's size makes it a rank.
    order = written(narrow.repartitionByRange("host", "path", "row").sortWithinPartitions("host", "path", "row").withColumn("number", F.monotonically_increasing_id()), "page-order")
    part = F.shiftright("number", 33)
    sizes = order.groupBy(part.alias("part")).agg(F.count(F.lit(1)).alias("n")).collect()  # a row per task, however many pages
    base, total = {}, 0
    for r in sorted(sizes, key=lambda r: r["part"]):
        base[r["part"]], total = total, total + r["n"]
    offsets = df.sparkSession.createDataFrame(sorted(base.items()), "part long, base long")
    ranked = order.withColumn("part", part).join(F.broadcast(offsets), "part").withColumn("rank", F.col("base") + F.col("number").bitwiseAND((1 << 33) - 1))
    places = F.array(*[F.col("rank") + d for d in range(-near, near + 1) if d])
    given = ranked.select(F.explode(places).alias("rank"), F.col("host").alias("from_host"), F.struct(*Offer._fields).alias("other"))
    asking = ranked.select("row", "host", "rank")
    met = asking.join(given, "rank").where(F.col("host") == F.col("from_host"))
    return met.groupBy("row").agg(F.collect_list("other").alias("around"))  # 2 * near at most


def extract(df: DataFrame, *, key: str = "page_id", url: str = "url", html: str = "html", near: int = 2) -> DataFrame:
    """key, url and text of every page, and how many of its lines differencing (n_differenced) and markup (n_by_markup) took."""
    around = neighbours(df, key=key, url=url, html=html, near=near)
    row = F.xxhash64(F.col(key), F.col(url), F.col(html)).alias("row")
    rows = df.select(row, F.col(key).alias("k"), F.col(url).alias("u"), F.col(html).alias("body")).join(around, "row", "left").drop("row")

    def step(batch: pa.RecordBatch) -> pa.RecordBatch:
        near_by = [[Offer(*(x[c] for c in Offer._fields)) for x in found or ()] for found in column_of(batch, "around").to_pylist()]
        found = [main_text(lines_of(page), offers) for page, offers in zip(column_of(batch, "body").to_pylist(), near_by, strict=True)]
        counts = {c: pa.array([x[i] for x in found], pa.int32()) for i, c in ((1, "n_differenced"), (2, "n_by_markup"))}
        return records(k=column_of(batch, "k"), u=column_of(batch, "u"), text=pa.array([x[0] for x in found], pa.string()), **counts)

    return map_texts(rows, step, f"k {dict(rows.dtypes)['k']}, u string, text string, n_differenced int, n_by_markup int", text="body").withColumnsRenamed({"k": key, "u": url})
