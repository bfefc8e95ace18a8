"""Main text of web pages by differencing a page with its nearest-URL neighbours, checked by structure.

1. A page is parsed once into lines: those inside of its article (article or main elements), those outside,
   and of the latter those that are marked as boilerplate (by their element, class, id or role).
2. Every page is differenced: its lines outside of articles are aligned with those of the nearest pages of
   other such lines before and after it in the order of URL paths in its host, and so are its lines inside.
   What a longest common subsequence holds is what the site repeats, and is to be deleted.
3. The check by structure follows. Where a page names its article, lines outside that differencing left go too,
   and lines inside that it took come back, as articles repeat passages (the README has the figures); but an
   article element after the page's first that neighbours repeat whole, beside other articles, is a box of the
   site and stays deleted. Where a page names none, differencing decides, among the lines not marked.

Edge cases: null and empty html give an empty text; character references are decoded, white
space runs become one blank; a page alone in its host keeps all its lines, and so do pages of
one host that are all equal, as then nothing tells text from frame; copies beside other pages
are aligned with those, once; null urls and urls without a host form a host of their own; repeated rows are
each extracted; columns other than the three are ignored; a text of any length is read whole; an
empty table gives no rows.
"""

from __future__ import annotations

from collections.abc import Iterator
from html.parser import HTMLParser
from itertools import chain
from operator import itemgetter

import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F
from pyspark.sql import types as T

from ._shared import Shelf, ranked, slices, tidy, working, written
from .url_rules import parts

_BLOCKS = frozenset(
    "address article aside blockquote body caption center dd details dialog dir div dl dt fieldset figcaption figure footer form"
    " h1 h2 h3 h4 h5 h6 head header hgroup hr html legend li main menu nav ol p pre section summary table tbody td tfoot th"
    " thead tr ul".split()
)
_VOID = frozenset("area base br col embed hr img input link meta source track wbr".split())
_BLANK = frozenset("br img wbr input".split())
_BOILERPLATE = frozenset(
    "head nav aside footer form script style noscript template iframe object svg canvas button select textarea option dialog menu title".split()
)
#: What no page shows as lines; other boilerplate is a line, if a marked one.
_NEVER = frozenset("head script style noscript template iframe object svg canvas textarea select option title".split())
_MARKS = frozenset(
    "ad ads adv advert adverts advertisement banner sponsor sponsored promo cookie cookies consent notice notices alert popup modal newsletter"
    " subscribe share sharing social sidebar menu nav navbar navigation breadcrumb breadcrumbs footer header masthead comment comments respond"
    " disqus reply replies related login signup search widget pagination pager skip".split()
)
#: What an article beside the page's own is called, as a whole or in part.
_ASIDE = frozenset("comment comments related teaser recommended promo sponsored advert advertisement".split())
_ROLES = frozenset("navigation banner contentinfo complementary search form alert dialog menu menubar".split())


#: Kinds of lines: marked as boilerplate, outside of articles, in a main element but no article; articles count on.
MARKED, OUTSIDE, MAIN = -1, 0, 1


class _Lines(HTMLParser):
    """Lines in page order, each with its kind; an article in an article belongs to it."""

    def __init__(self) -> None:
        super().__init__(convert_charrefs=True)
        self.stack: list[tuple[str, bool, bool, bool]] = []
        self.skipping = self.silent = 0
        self.inside: list[int] = []
        self.articles = MAIN
        self.text: list[str] = []
        self.marked: list[str] = []
        self.lines: list[str] = []
        self.kinds: list[int] = []

    def end_block(self) -> None:
        for text, kind in ((self.text, self.inside[-1] if self.inside else OUTSIDE), (self.marked, MARKED)):
            if text and (line := " ".join("".join(text).split())):
                self.lines.append(line)
                self.kinds.append(kind)
            text.clear()

    def boilerplate(self, tag: str, attributes: dict[str, str]) -> bool:
        marks = set()
        for name in ("class", "id"):
            marks.update("".join(c if c.isalnum() else " " for c in attributes.get(name, "").lower()).split())
        if tag in ("article", "main"):  # as a whole word of its class: an article may well say "has-sidebar"
            named = set(f"{attributes.get('class', '')} {attributes.get('id', '')}".lower().split())
            return bool(named & _MARKS or marks & _ASIDE)
        if tag in ("body", "html"):
            return bool(marks & {"comment", "comments"})
        if tag == "header":
            return not self.inside
        style = attributes.get("style", "").replace(" ", "").lower()
        return (
            tag in _BOILERPLATE or bool(marks & _MARKS) or attributes.get("role", "").lower() in _ROLES
            or "hidden" in attributes or attributes.get("aria-hidden", "").lower() == "true" or "display:none" in style
        )

    def pop(self) -> str:
        tag, skips, article, silent = self.stack.pop()
        self.skipping -= skips
        self.silent -= silent
        if article:
            self.end_block()
            self.inside.pop()
        return tag

    def handle_starttag(self, tag: str, attrs: list[tuple[str, str | None]]) -> None:
        if tag in _BLANK:
            self.text.append(" ")
            self.marked.append(" ")
        if tag in _BLOCKS:
            self.end_block()
            if any(t == "p" for t, *_ in self.stack[-8:]):  # a block ends an open paragraph
                while self.pop() != "p":
                    pass
        if tag in _VOID:
            return
        if tag == "li" or tag in ("td", "tr"):
            if any(t == tag for t, *_ in self.stack[-4:]) and self.stack[-1][0] not in ("ul", "ol", "table", "tbody"):
                while self.pop() != tag:
                    pass
        attributes = {k: v or "" for k, v in attrs}
        skips = self.boilerplate(tag, attributes)
        article = not skips and (tag in ("article", "main") or attributes.get("role", "").lower() == "main")
        if article:
            self.end_block()
            if tag == "article" and (not self.inside or self.inside[-1] == MAIN):
                self.articles += 1
                self.inside.append(self.articles)
            else:
                self.inside.append(self.inside[-1] if self.inside else MAIN)
        silent = tag in _NEVER
        self.stack.append((tag, skips, article, silent))
        self.skipping += skips
        self.silent += silent

    def handle_startendtag(self, tag: str, attrs) -> None:
        self.handle_starttag(tag, attrs)
        if tag not in _VOID:
            self.handle_endtag(tag)

    def handle_endtag(self, tag: str) -> None:
        if tag in _BLOCKS:
            self.end_block()
        if any(t == tag for t, *_ in self.stack):
            while self.pop() != tag:
                pass

    def handle_data(self, data: str) -> None:
        if not self.silent:
            (self.marked if self.skipping else self.text).append(data)

    def unknown_decl(self, data: str) -> None:
        return


def parsed(html: str | None) -> tuple[list[str], list[int]]:
    """Lines of a page and their kinds."""
    parser = _Lines()
    parser.feed(html or "")
    parser.close()
    while parser.stack:
        parser.end_block()
        parser.pop()
    parser.end_block()
    return parser.lines, parser.kinds


def lines(html: str | None) -> tuple[list[str], list[str]]:
    """(lines of the article, lines outside of it that are not marked) of a page."""
    found = list(zip(*parsed(html), strict=True))
    return [x for x, kind in found if kind > OUTSIDE], [x for x, kind in found if kind == OUTSIDE]


ALIGN_BITS = 1 << 28


def _rows(a: list, b: list) -> list[int]:
    """For each line of a, a word with a bit a line of b: it is clear where the longest common subsequence of what
    has been read of a with b up to that line is one longer than up to the line before. First the empty reading."""
    places: dict = {}
    for j, y in enumerate(b):
        places[y] = places.get(y, 0) | 1 << j
    every = (1 << len(b)) - 1
    row, out = every, [every]
    for x in a:
        both = row & places.get(x, 0)
        row = (row + both | row - both) & every
        out.append(row)
    return out


def _lengths(row: int, n: int) -> list[int]:
    """How long the subsequence is with each beginning of b, from a row of _rows."""
    out = [0]
    for j in range(n):
        out.append(out[-1] + (~row >> j & 1))
    return out


def _aligned(a: list, b: list, low: int, out: set[int]) -> None:
    """Add to out the places in a, counted from low, of a longest common subsequence with b. Where the rows would take
    over ALIGN_BITS, a is halved and b is cut where both halves' subsequences are longest together, so that a
    row is held and no table."""
    if not a or not b:
        return
    if len(a) > 1 and (len(a) + 1) * len(b) > ALIGN_BITS:
        half = len(a) // 2
        left = _lengths(_last_row(a[:half], b), len(b))
        right = _lengths(_last_row(a[half:][::-1], b[::-1]), len(b))
        cut = max(range(len(b) + 1), key=lambda j: left[j] + right[len(b) - j])
        _aligned(a[:half], b[:cut], low, out)
        _aligned(a[half:], b[cut:], low + half, out)
        return
    rows, i, j = _rows(a, b), len(a), len(b)
    while i and j:
        if rows[i] >> (j - 1) & 1:
            j -= 1
        elif not rows[i - 1] >> (j - 1) & 1:
            i -= 1
        else:
            out.add(low + i - 1)
            i, j = i - 1, j - 1


def _last_row(a: list, b: list) -> int:
    places: dict = {}
    for j, y in enumerate(b):
        places[y] = places.get(y, 0) | 1 << j
    every = (1 << len(b)) - 1
    row = every
    for x in a:
        both = row & places.get(x, 0)
        row = (row + both | row - both) & every
    return row


def common(mine: list, other: list) -> set[int]:
    """Places in mine of a longest common subsequence with other; shared ends are set apart first, the middle is
    aligned by words of bits, a word a line."""
    low, n, m = 0, len(mine), len(other)
    while low < min(n, m) and mine[low] == other[low]:
        low += 1
    while n > low and m > low and mine[n - 1] == other[m - 1]:
        n, m = n - 1, m - 1
    out = set(range(low)) | set(range(n, len(mine)))
    own, its = set(mine[low:n]), set(other[low:m])
    kept = [k for k in range(low, n) if mine[k] in its]
    found: set[int] = set()
    _aligned([mine[k] for k in kept], [x for x in other[low:m] if x in own], 0, found)
    return out | {kept[k] for k in found}


#: Bits of a line's mark: a neighbour repeats it; one that has several articles does.
REPEATED, BOXED = 1, 2


def differenced(mine: list, others: list[tuple[list, bool]]) -> bytes:
    """A mark a line of mine. others: lines of the neighbours, and whether they stand in several articles."""
    marks = bytearray(len(mine))
    for other, several in others:
        for k in common(mine, other):
            marks[k] |= REPEATED | (BOXED if several else 0)
    return bytes(marks)


def checked(texts: list[str], kinds: list[int], outside: bytes | None, inside: bytes | None) -> tuple[str, int, int]:
    """(text, lines that differencing deleted, those of them that structure gave back). texts: lines that are not marked;
    outside, inside: what differencing found, of the lines outside (if all are marked, of those) and inside of articles."""
    repeated = sum(m & REPEATED for m in outside or b"") + sum(m & REPEATED for m in inside or b"")
    if any(kinds):
        own = [(x, kind) for x, kind in zip(texts, kinds, strict=True) if kind > OUTSIDE]
        marks = inside or bytes(len(own))
        articles = [kind for _, kind in own if kind > MAIN]
        boxes = set(articles) - set(articles[:1]) - {kind for (_, kind), m in zip(own, marks, strict=True) if not m & BOXED}
        given = sum(m & REPEATED for (_, kind), m in zip(own, marks, strict=True) if kind not in boxes)
        return "\n\n".join(x for x, kind in own if kind not in boxes), repeated, given
    marks = outside if outside and texts else bytes(len(texts))
    kept = [x for x, m in zip(texts, marks, strict=True) if not m]
    return ("\n\n".join(kept), repeated, 0) if kept else ("\n\n".join(texts), repeated, repeated if texts else 0)


def _keys(found: list[str]) -> list[int]:
    import xxhash

    return [xxhash.xxh3_64_intdigest(x.encode(errors="surrogatepass")) - (1 << 63) for x in found]


_PAGE = T.StructType(
    [T.StructField("texts", T.ArrayType(T.StringType())), T.StructField("kinds", T.ArrayType(T.IntegerType())),
     *(T.StructField(x, T.ArrayType(T.LongType())) for x in ("inside", "outside", "framed"))]
)


def _parse(schema: pa.Schema, article_aware: bool):
    """Of (id, url, html): lines that are not marked with their kinds, and numbers that stand for lines: those inside
    of articles, those outside to be judged (if all are marked, those), and all outside."""

    def page(html: str | None) -> tuple[list, list, list, list, list]:
        found, kinds = parsed(html)
        if not article_aware:
            kinds = [min(kind, OUTSIDE) for kind in kinds]
        keys = list(zip(_keys(found), kinds, strict=True))
        framed = [key for key, kind in keys if kind <= OUTSIDE]
        return (
            [x for x, kind in zip(found, kinds, strict=True) if kind >= OUTSIDE], [kind for kind in kinds if kind >= OUTSIDE],
            [key for key, kind in keys if kind > OUTSIDE], [key for key, kind in keys if kind == OUTSIDE] or framed, framed,
        )

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in batches:
            for at in range(0, batch.num_rows, 512):
                part = batch.slice(at, 512)
                columns = zip(*map(page, part.column(2).to_pylist()), strict=True)
                made = [pa.array(list(x), type=f.type) for x, f in zip(columns, list(schema)[2:], strict=True)]
                yield pa.RecordBatch.from_arrays([part.column(0), part.column(1), *made], schema=schema)

    return run


#: Consecutive groups that are differenced in one block; a block has its next neighbours too.
BLOCK = 256
_MARKS_TYPE = "first long, strand int, marks binary"


def _difference(block: int):
    """Of (block, at, row, strand, host, mine, other, several) in the order of blocks and places: marks of each
    group in its own block, where any is set. Three groups are held at a time."""
    schema = pa.schema([("first", pa.int64()), ("strand", pa.int32()), ("marks", pa.binary())])
    place = itemgetter("block", "strand", "host")

    def sent(found: list[tuple]) -> pa.RecordBatch:
        return pa.RecordBatch.from_arrays([pa.array([x[i] for x in found], type=f.type) for i, f in enumerate(schema)], schema=schema)

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        before = now = None
        out: list[tuple] = []
        for after in chain((r for part in slices(batches, 64) for r in part.to_pylist()), [None]):
            if now and now["at"] // block == now["block"]:
                marks = differenced(now["mine"], [(x["other"], x["several"]) for x in (before, after) if x and place(x) == place(now)])
                if any(marks):
                    out.append((now["row"], now["strand"], marks))
            before, now = now, after
            if len(out) == 256:
                yield sent(out)
                out = []
        yield sent(out)

    return run


def _apply(schema: pa.Schema):
    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in batches:
            for at in range(0, batch.num_rows, 512):
                part = batch.slice(at, 512)
                own = [checked(*x) for x in zip(*(part.column(k).to_pylist() for k in range(2, 6)), strict=True)]
                made = [pa.array([x[i] for x in own], type=f.type) for i, f in enumerate(list(schema)[2:])]
                yield pa.RecordBatch.from_arrays([part.column(0), part.column(1), *made], schema=schema)

    return run


def _marked(shelf: Shelf) -> DataFrame:
    """(row, on_outside, on_inside) of the pages some line of which differencing deletes. A written table."""
    several = F.array_max("kinds") > F.array_min(F.filter("kinds", lambda k: k > MAIN))
    strands = shelf.rows().select("row", "url", F.explode(F.array(
        F.struct(F.lit(0).alias("strand"), F.col("outside").alias("mine"), F.col("framed").alias("other"), F.lit(False).alias("several")),
        F.struct(F.lit(1).alias("strand"), F.col("inside").alias("mine"), F.col("inside").alias("other"), F.coalesce(several, F.lit(False)).alias("several")),
    )).alias("s")).select("row", "url", "s.*").where(F.size("mine") > 0)
    digest = F.array_join(F.col("mine").cast("array<string>"), ",")
    located = parts(strands.select("row", "strand", digest.alias("lines"), "url"))
    group = F.unhex(F.sha2(F.concat_ws("|", "strand", "lines", "host"), 256)).alias("group")
    located = located.select("row", "strand", "host", "path", group)
    groups = located.groupBy("group").agg(F.min(F.struct("path", "row", "strand", "host")).alias("first"))
    groups = written(groups.select("group", "first.*"), "pages-groups")
    order = ranked(groups.select("row", "strand", "host", "path"), ["strand", "host", "path", "row"], "at", "pages-order")
    placed = order.drop("path").join(strands.select("row", "strand", "mine", "other", "several"), ["row", "strand"])
    own = F.floor(F.col("at") / BLOCK)
    blocks = F.explode(F.array_distinct(F.array(own, F.floor((F.col("at") - 1) / BLOCK), F.floor((F.col("at") + 1) / BLOCK)))).alias("block")
    placed = placed.select(blocks, "at", "row", "strand", "host", "mine", "other", "several").repartition("block").sortWithinPartitions("block", "at")
    marks = written(placed.mapInArrow(tidy(_difference(BLOCK)), _MARKS_TYPE), "pages-marks")
    firsts = groups.select("group", F.col("row").alias("first"), "strand").join(marks, ["first", "strand"]).select("group", "marks")
    mine = located.select("row", "strand", "group").join(written(firsts, "pages-firsts"), "group")
    of = lambda strand: F.max(F.when(F.col("strand") == strand, F.col("marks")))
    return written(mine.groupBy("row").agg(of(0).alias("on_outside"), of(1).alias("on_inside")), "pages-marked")


def main_text(pages: DataFrame, id_col: str = "page_id", url_col: str = "url", html_col: str = "html", article_aware: bool = True) -> DataFrame:
    """(id, url, text, n_repeated, n_restored) of every page: n_repeated lines are deleted by differencing, n_restored
    of them given back by structure. article_aware=False takes no element for an article, as a comparison.

    Pages of equal lines in a host are one group, which lies where its first URL lies, and is aligned once: its
    neighbours are the nearest groups of other lines. Groups are ordered by (host, path) over the cluster and
    dealt in blocks, so a host with a third of all pages is many partitions. Texts are written once and never shuffled.
    """
    from pyspark.sql.pandas.types import to_arrow_schema

    source = pages.select(F.col(id_col).alias("id"), F.col(url_col).alias("url"), F.col(html_col).alias("html"))
    keep = source.schema.fields[:2]
    page = T.StructType([*keep, *_PAGE.fields])
    shelf = Shelf(source.mapInArrow(tidy(_parse(to_arrow_schema(page), article_aware)), page), "pages-shelf", "row", 250_000)
    with working(pages.sparkSession) as kept:
        marked = _marked(shelf)
        kept(marked.scratch)
    result = T.StructType([*keep, T.StructField("text", T.StringType()), T.StructField("n_repeated", T.LongType()), T.StructField("n_restored", T.LongType())])
    both = shelf.match(marked, "left", "pages-left", ["id", "url", "texts", "kinds"]).drop("row")
    out = both.mapInArrow(tidy(_apply(to_arrow_schema(result))), result)
    return out.select(F.col("id").alias(id_col), F.col("url").alias(url_col), "text", "n_repeated", "n_restored")
