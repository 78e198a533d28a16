"""Main text of web pages: the page's own structure, and nearest-URL page differencing.

Pages are ordered by host and URL path; each is aligned, line by line, with the nearest
page before and the nearest page after it on its host by a longest common subsequence.
Lines that they share are the site's, not the page's, and are deleted. Copies are no
neighbours: of a run of copies each page is held against the pages around the run. Where
a page marks its article (an article or main element, or a container named so), it says
itself what is its text: there no line is deleted for being shared, since two articles
may quote the same passage.

The order is cut into stretches of about PAGES_A_BLOCK pages, or of BLOCK_BYTES where
there are very many, by a bounded sample of URLs; the first and last page of a stretch is
dealt to its neighbours too, so that one host of any size is spread and no pair is
missed. A run of copies doesn't reach over the end of a stretch.
"""

from __future__ import annotations

import html
import re
from bisect import bisect_left, bisect_right
from collections import defaultdict
from collections.abc import Iterator
from dataclasses import dataclass, field

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from pathsieve.llm.shared import own_columns, text_slices

PAGES_A_BLOCK, SMALL_BLOCKS, BLOCK_BYTES, SAMPLED_A_BLOCK = 200, 4096, 1 << 24, 16
#: A page that shares more than this of another's text, as far as the structure leaves it, is a copy.
COPY = 0.9
#: Pairs of equal lines for each line beyond which the alignment goes by rows of bits.
_MANY = 32

_TOKEN = re.compile(r"<!--.*?(?:-->|\Z)|<(script|style|noscript|template|svg|iframe|object|textarea|select|button|math|canvas|audio|video|head)\b[^>]*>.*?(?:</\1\s*>|\Z)|<[!?][^>]*>|<(/?)([A-Za-z][\w:-]*)([^>]*)>|[^<]+|<", re.S | re.I)
_ATTRIBUTE = re.compile(r"""(class|id|role|style|aria-hidden|hidden)\s*(?:=\s*("[^"]*"|'[^']*'|[^\s"'>]+))?""", re.I)
_NAME = re.compile(r"[a-z0-9]+")
_SPACE = re.compile(r"\s+")

# Elements that stand for a block, elements that never close, elements and names that aren't the article.
BLOCKS = frozenset("address article aside blockquote body center dd details dialog div dl dt fieldset figcaption figure footer form h1 h2 h3 h4 h5 h6 header hr html legend li main menu nav ol p pre section summary table tbody td tfoot th thead tr ul".split())
VOID = frozenset("area base br col embed hr img input link meta param source track wbr".split())
NOT_TEXT = frozenset("nav header footer aside form menu dialog label fieldset".split())
NOT_TEXT_NAMES = frozenset("nav navbar navigation menu breadcrumb breadcrumbs header masthead footer sidebar aside widget notice notices cookie cookies consent gdpr banner ad ads advert adverts advertisement advertising sponsor sponsored promo popup modal overlay form search login signup newsletter subscribe subscription share sharing social related recommended comment comments disqus reply replies pagination pager toolbar alert complementary contentinfo dialog disclaimer teaser recommendations".split())
ARTICLE, ARTICLE_NAMES = {"article": 3, "main": 2}, frozenset("article content post entry story main".split())


@dataclass
class Page:
    """Lines in page order: their texts, how plainly each is marked as the article's (0: not at all), whether the structure drops it."""

    lines: list[str] = field(default_factory=list)
    inside: list[int] = field(default_factory=list)
    dropped: list[bool] = field(default_factory=list)


def _names(attributes: str) -> tuple[set[str], bool]:
    names: set[str] = set()
    hidden = False
    for m in _ATTRIBUTE.finditer(attributes):
        key, value = m[1].lower(), (m[2] or "").strip("\"'").lower()
        if key in ("class", "id", "role"):
            names.update(_NAME.findall(value))
        elif key == "style":
            hidden |= "display:none" in value.replace(" ", "")
        else:
            hidden |= key == "hidden" or value == "true"
    return names, hidden


def parse(source: str | None) -> Page:
    page, held = Page(), []
    stack: list[tuple[str, int, bool]] = []  # element, mark of the article, dropped
    inside, dropped = 0, False

    def close() -> None:
        nonlocal held
        if held:
            text = _SPACE.sub(" ", html.unescape("".join(held))).strip()
            if text:
                page.lines.append(text)
                page.inside.append(inside)
                page.dropped.append(dropped)
            held = []

    for m in _TOKEN.finditer(source or ""):
        tag = m[3]
        if tag is None:
            if m[0][0] != "<" or m[0] == "<":
                held.append(m[0])
            continue
        tag = tag.lower()
        if tag == "br":
            held.append(" ")
        if tag in VOID and tag != "hr":
            continue
        if tag in BLOCKS:
            close()
            if stack and stack[-1][0] == "p":  # a block ends a paragraph
                stack.pop()
        if m[2]:
            for k in range(len(stack) - 1, -1, -1):
                if stack[k][0] == tag:
                    if tag not in BLOCKS and stack[k][2] and not (k and stack[k - 1][2]):
                        close()
                    del stack[k:]
                    break
        elif tag in BLOCKS or m[4]:
            names, hidden = _names(m[4]) if m[4] else ((), False)
            whole = tag in ("html", "body", "article", "main")
            was_in, was_out = (stack[-1][1], stack[-1][2]) if stack else (0, False)
            out = was_out or hidden or tag in NOT_TEXT or (not whole and not NOT_TEXT_NAMES.isdisjoint(names)) or (whole and "comment" in names)
            if tag not in BLOCKS and out and not was_out:
                close()
            if not m[4].endswith("/"):
                stack.append((tag, max(was_in, ARTICLE.get(tag, 0), int(tag in ("div", "section", "td") and not ARTICLE_NAMES.isdisjoint(names))), out))
        inside, dropped = (stack[-1][1], stack[-1][2]) if stack else (0, False)
    close()
    return page


def _lengths(a: list[str], b: list[str]) -> np.ndarray:
    """Length of a longest common subsequence of a and b[:k], for every k: a row of bits for each line of a."""
    places: dict[str, int] = defaultdict(int)
    for k, x in enumerate(b):
        places[x] |= 1 << k
    full = (1 << len(b)) - 1
    row = full
    for x in a:
        if found := row & places.get(x, 0):
            row = (row + found | row - found) & full
    bits = np.unpackbits(np.frombuffer(row.to_bytes(-(-len(b) // 8) or 1, "little"), np.uint8), bitorder="little")[: len(b)]
    return np.r_[0, np.cumsum(1 - bits.astype(np.int64))]


def common(a: list[str], b: list[str]) -> list[int]:
    """Places in a of a longest common subsequence with b. Memory is linear in the lines, however often some repeat."""
    where = defaultdict(list)
    for k, x in enumerate(b):
        where[x].append(k)
    if len(a) > 1 and sum(len(where.get(x, ())) for x in a) > _MANY * (len(a) + len(b)):
        half = len(a) // 2  # each half has its share of b
        ahead, back = _lengths(a[:half], b), _lengths(a[:half - 1 : -1], b[::-1])[::-1]
        cut = int((ahead + back).argmax())
        return common(a[:half], b[:cut]) + [half + k for k in common(a[half:], b[cut:])]
    tails: list[int] = []
    nodes: list[tuple[int, int]] = []  # (place in a, previous node)
    last: list[int] = []
    for i, x in enumerate(a):
        for j in reversed(where.get(x, ())):
            k = bisect_left(tails, j)
            nodes.append((i, last[k - 1] if k else -1))
            if k == len(tails):
                tails.append(j)
                last.append(len(nodes) - 1)
            else:
                tails[k], last[k] = j, len(nodes) - 1
    out, k = [], last[-1] if last else -1
    while k >= 0:
        out.append(nodes[k][0])
        k = nodes[k][1]
    return out[::-1]


def is_copy(page: Page, other: Page) -> bool:
    """Whether the other page shares nearly all lines that the structure doesn't drop."""
    size = lambda some: sum(len(page.lines[k]) for k in some if not page.dropped[k])
    return size(common(page.lines, other.lines)) > COPY * size(range(len(page.lines)))


def main_text(page: Page, neighbours: list[Page]) -> tuple[str, int]:
    """The page's text, and how many of its lines a neighbour shares."""
    shared = {k for other in neighbours for k in common(page.lines, other.lines)}
    mark = max((i for i, d in zip(page.inside, page.dropped, strict=True) if not d), default=0)  # the plainest mark on the page counts
    kept = [line for k, line in enumerate(page.lines) if not page.dropped[k] and (page.inside[k] == mark if mark else k not in shared)]
    return "\n\n".join(kept), len(shared)


def place(url: str | None) -> tuple[str, str]:
    """(host, path) in lower case, without scheme, port, query and fragment."""
    rest = re.split(r"[?#]", (url or "").split("//", 1)[-1], maxsplit=1)[0].lower()
    host, _, path = rest.partition("/")
    return host.split(":")[0], path


def _key(url: str | None, page_id: int | None) -> str:
    host, path = place(url)
    return f"{host}\x00{path}\x00{-1 if page_id is None else page_id:020d}"


def extract(pages: DataFrame) -> DataFrame:
    """A row for each row of pages (page_id, url, html): (page_id, url, text, n_chars, n_lines, n_shared).

    text is empty if the page has none, or html is null. Pages without a url are one
    host. Repeated rows get rows each; other columns aren't read.
    """
    pages = own_columns(pages, "page_id", "url", "html")
    total, size = pages.agg(F.count(F.lit(1)), F.coalesce(F.sum(F.octet_length("html")), F.lit(0))).first()
    blocks = max(1, min(SMALL_BLOCKS, -(-total // PAGES_A_BLOCK)), -(-size // BLOCK_BYTES))
    tasks = max(int(pages.sparkSession.conf.get("spark.sql.shuffle.partitions")), -(-size // (2 * BLOCK_BYTES)))
    share = min(1.0, SAMPLED_A_BLOCK * blocks / max(total, 1))
    sampled = pages.where(F.pmod(F.xxhash64("page_id", "url"), F.lit(1 << 30)) < share * (1 << 30)).select("url", "page_id").limit(2 * SAMPLED_A_BLOCK * blocks).collect()  # a sample of bounded size, for the stretches' edges alone
    keys = sorted(_key(r["url"], r["page_id"]) for r in sampled)
    edges = sorted({keys[k * len(keys) // blocks] for k in range(1, blocks)}) if keys else []

    def ends(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        least: dict[int, str] = {}
        most: dict[int, str] = {}
        for batch in batches:
            for url, page in zip(batch.column("url").to_pylist(), batch.column("page_id").to_pylist(), strict=True):
                key = _key(url, page)
                b = bisect_right(edges, key)
                if b not in least or key < least[b]:
                    least[b] = key
                if b not in most or key > most[b]:
                    most[b] = key
        yield pa.RecordBatch.from_pydict({"block": pa.array(list(least), pa.int32()), "least": pa.array(list(least.values()), pa.string()), "most": pa.array([most[b] for b in least], pa.string())})

    found = sorted(pages.select("url", "page_id").mapInArrow(ends, "block int, least string, most string").groupBy("block").agg(F.min("least"), F.max("most")).collect())  # a row for each stretch, about 100 bytes for 16 MB of pages
    before = {b[1]: a[0] for a, b in zip(found, found[1:], strict=False)}  # first key of a stretch -> the stretch before
    after = {a[2]: b[0] for a, b in zip(found, found[1:], strict=False)}

    def deal(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for whole in batches:
            for batch in text_slices(whole, "html"):
                rows, block, key_of, ghost = [], [], [], []
                for k, (url, page) in enumerate(zip(batch.column("url").to_pylist(), batch.column("page_id").to_pylist(), strict=True)):
                    key = _key(url, page)
                    for b, g in ((bisect_right(edges, key), False), (before.get(key), True), (after.get(key), True)):
                        if b is not None:
                            rows.append(k)
                            block.append(b)
                            key_of.append(key)
                            ghost.append(g)
                yield pa.RecordBatch.from_arrays([*(batch.column(c).take(pa.array(rows, pa.int64())) for c in ("page_id", "url", "html")), pa.array(block, pa.int32()), pa.array(key_of, pa.string()), pa.array(ghost, pa.bool_())], ["page_id", "url", "html", "block", "key", "ghost"])

    def compare(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        """Rows come sorted by (block, key); a page waits for the one after it."""
        before: tuple | None = None
        run: list[tuple] = []  # pages in a row that are copies
        out: dict[str, list] = {c: [] for c in ("page_id", "url", "text", "n_chars", "n_lines", "n_shared")}

        def settle(following: tuple | None) -> None:
            nonlocal before
            for block, host, ghost, page, page_id, url in run:
                if not ghost:
                    text, shared = main_text(page, [x[3] for x in (before, following) if x is not None and x[:2] == (block, host)])
                    for c, v in zip(out, (page_id, url, text, len(text), len(page.lines), shared), strict=True):
                        out[c].append(v)
            if run:
                before = run[-1]
            run.clear()

        def ready() -> pa.RecordBatch:
            batch = pa.RecordBatch.from_arrays([pa.array(v, t) for v, t in zip(out.values(), (pa.int64(), pa.string(), pa.string(), pa.int64(), pa.int64(), pa.int64()), strict=True)], list(out))
            for v in out.values():
                v.clear()
            return batch

        for whole in batches:
            for batch in text_slices(whole, "html"):
                for page_id, url, source, block, key, ghost in zip(*(batch.column(c).to_pylist() for c in ("page_id", "url", "html", "block", "key", "ghost")), strict=True):
                    now = (block, key.split("\x00", 1)[0], ghost, parse(source), page_id, url)
                    if run and not (run[-1][:2] == now[:2] and is_copy(now[3], run[-1][3])):
                        settle(now)
                    run.append(now)
                yield ready()
        settle(None)
        yield ready()

    dealt = pages.mapInArrow(deal, "page_id long, url string, html string, block int, key string, ghost boolean")
    return dealt.repartition(tasks, "block").sortWithinPartitions("block", "key", "ghost").mapInArrow(compare, "page_id long, url string, text string, n_chars long, n_lines long, n_shared long")
