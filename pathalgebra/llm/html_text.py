"""Main text of web pages: nearest-URL page differencing, guided by structure.

Pages of a host are sorted by URL path; each is paired with the neighbour whose
path has the longer beginning in common, and the lines of the two are aligned by
longest common subsequence.  Shared lines are evidence against the element that
holds them: over all pages of a host, an element (its path of names and classes)
whose lines are nearly all shared belongs to the template and is deleted whole.  An
element whose lines are mostly its own keeps what it shares, so articles keep the
passages that they have in common.

Differencing can't see what differs from page to page without being text of the
article: adverts, menus of near pages, forms.  Those are told by their elements.  On
pages without an ``article`` or ``main`` element shared lines go one by one as well.
"""

from __future__ import annotations

import html as entities
import re
from collections.abc import Iterator

import pyarrow as pa
import xxhash
from pyspark import TaskContext
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from pathalgebra.runtime import checkpointed, stored

#: Elements that end a line of text; that never hold an article's text; whose content isn't text.
_BLOCK = frozenset(
    "address article aside blockquote body caption center dd details div dl dt fieldset figcaption figure footer form h1 h2 h3 h4 h5 h6 head header hr html legend li main menu nav ol p pre section summary table tbody td tfoot th thead tr ul".split()
)
_DROP = frozenset("nav header footer aside form head menu dialog button select option label fieldset iframe object noscript template svg canvas map audio video".split())
_RAW = re.compile(r"<(script|style|textarea|xmp)\b.*?(?:</\1\s*>|\Z)", re.I | re.S)
_VOID = frozenset("area base br col embed hr img input link meta param source track wbr".split())
#: Fixed value: names that sites give to what isn't the article.
_ASIDE = re.compile(
    r"(?:^|[\s_-])(?:ads?|adverts?|advertisement|adsbygoogle|banner|breadcrumbs?|comments?|cookies?|disqus|footer|header|masthead|menu|modal|nav|navbar|navigation|newsletter|notice|popup|promo|related|share|sharing|sidebar|social|sponsor|sponsored|subscribe|toolbar|widget)(?:$|[\s_-])",
    re.I,
)
_TAG = re.compile(r"<!--.*?(?:-->|\Z)|<[!?][^>]*(?:>|\Z)|<(/?)([a-zA-Z][^\s/>]*)((?:[^>\"']|\"[^\"]*\"|'[^']*')*)(?:>|\Z)", re.S)
_NAMES = re.compile(r"(?:class|id|role)\s*=\s*(?:\"([^\"]*)\"|'([^']*)'|([^\s\"'>]+))", re.I)
_URL = re.compile(r"^[a-zA-Z][a-zA-Z0-9+.-]*://([^/?#]*)([^?#]*)")

#: Elements that hold passages; the path of those that are open names the place of a line.
_BOX = frozenset("article aside blockquote details div dl figure footer form header main nav ol section table ul".split())
_CLASS = re.compile(r"(?:class|id)\s*=\s*(?:\"([^\"]*)\"|'([^']*)'|([^\s\"'>]+))", re.I)

_PARSED = "page_id long, url string, key long, host string, path string, article boolean, lines array<string>, boxes array<long>, roles array<int>"
_PARSED_ARROW = pa.schema([
    ("page_id", pa.int64()), ("url", pa.string()), ("key", pa.int64()), ("host", pa.string()), ("path", pa.string()), ("article", pa.bool_()),
    ("lines", pa.list_(pa.string())), ("boxes", pa.list_(pa.int64())), ("roles", pa.list_(pa.int32())),
])
#: Roles of lines: free, inside the article, inside an element that never holds article text.
FREE, ARTICLE, DROPPED = 0, 1, 2

#: An element is template if nine tenths of its lines are shared, on this many pages of the host at least.
LEAST_SHARE, LEAST_PAGES = 0.9, 10
_SALTS = 64


def _hash(text: str) -> int:
    return xxhash.xxh3_64_intdigest(text.encode("utf-8", "surrogatepass")) - (1 << 63)


def text_lines(source: str | None) -> tuple[list[tuple[str, int, int]], bool]:
    """Lines of a page as (text, role, number of the path of open elements), and whether it has an article.

    A line is the text between two block borders, with character references
    decoded and white space turned into single blanks.  Unclosed elements are
    closed by the end of the page; a dropped element that was never closed ends
    where the article begins.
    """
    lines: list[tuple[str, int, int]] = []
    held: list[str] = []
    boxes: list[tuple[str, int]] = [("", 0)]
    source = _RAW.sub(" ", source or "")
    article = 0
    dropped: list[tuple[str, int]] = []  # name of the dropped element, depth of the same name inside
    has_article = False

    def flush() -> None:
        if held:
            text = " ".join(entities.unescape("".join(held)).split())
            held.clear()
            if text:
                lines.append((text, DROPPED if dropped else ARTICLE if article else FREE, boxes[-1][1]))

    at = 0
    for m in _TAG.finditer(source):
        if m.start() > at:
            held.append(source[at : m.start()])
        at = m.end()
        if m[2] is None:
            continue
        closing, name = m[1], m[2].lower()
        if name == "br":
            held.append(" ")
            continue
        if name in _BLOCK or name in _DROP:
            flush()
        if name in _VOID:
            continue
        if name in _BOX and not m[3].endswith("/"):
            if not closing:
                named = _CLASS.search(m[3])
                said = re.sub(r"\d+", "0", next(filter(None, named.groups()), "")) if named else ""
                boxes.append((name, _hash(f"{boxes[-1][1]} {name} {said}")))
            else:
                for k in range(len(boxes) - 1, 0, -1):
                    if boxes[k][0] == name:
                        del boxes[k:]
                        break
        if name in ("article", "main"):
            if closing:
                if not dropped:
                    article = max(0, article - 1)
            else:
                if not article:
                    dropped.clear()
                if not dropped:
                    article += 1
                    has_article = True
        elif name == "body" and not closing and dropped and dropped[-1][0] == "head":
            dropped.clear()
        elif dropped and dropped[-1][0] == name:
            depth = dropped[-1][1] + (-1 if closing else 1)
            if depth:
                dropped[-1] = (name, depth)
            else:
                flush()
                dropped.pop()
        elif not closing and (name in _DROP or ("=" in m[3] and any(_ASIDE.search(next(filter(None, v), "")) for v in _NAMES.findall(m[3])))) and not (m[3].endswith("/")):
            flush()
            dropped.append((name, 1))
    if at < len(source):
        rest = source[at:]
        held.append(rest if not re.match(r"<[a-zA-Z/!]", rest) else "")
    flush()
    return lines, has_article


def common_lines(mine: list[int], other: list[int]) -> set[int]:
    """Places in ``mine`` that a longest common subsequence with ``other`` takes.

    Bit-parallel: bit i of a row is 0 where the length grows at place i; the rows
    are kept, so walking back gives the places.
    """
    shared = set(mine) & set(other)
    places = [k for k, x in enumerate(mine) if x in shared]
    a, b = [mine[k] for k in places], [x for x in other if x in shared]
    if not a:
        return set()
    full = (1 << len(a)) - 1
    where: dict[int, int] = {}
    for k, x in enumerate(a):
        where[x] = where.get(x, 0) | 1 << k
    rows, v = [], full
    for x in b:
        u = v & where.get(x, 0)
        v = ((v + u) | (v - u)) & full
        rows.append(v)
    taken, i, j = set(), len(a), len(b)
    while i and j:
        if rows[j - 1] >> (i - 1) & 1:
            i -= 1
        else:
            j -= 1
            if not (j and not rows[j - 1] >> (i - 1) & 1):
                i -= 1
                taken.add(places[i])
    return taken


def _address(url: str | None) -> tuple[str, str]:
    m = _URL.match(url or "")
    return (m[1].lower(), m[2]) if m else ("", url or "")


def _common(a: str, b: str) -> int:
    n = 0
    for x, y in zip(a, b, strict=False):
        if x != y:
            break
        n += 1
    return n


def _key(page_id: int | None, url: str | None, source: str | None) -> int:
    said = f"{page_id}\0{url is None}\0{url or ''}\0{source is None}\0".encode("utf-8", "surrogatepass") + (source or "").encode("utf-8", "surrogatepass")
    return xxhash.xxh3_64_intdigest(said) - (1 << 63)


def parsed_pages(pages: DataFrame) -> DataFrame:
    """Every page's lines with their elements and roles; pages are parsed here only."""

    def parse(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in batches:
            for at in range(0, len(batch), 500):
                out: list[list] = [[] for _ in _PARSED_ARROW]
                for page_id, url, source in zip(*(c.to_pylist() for c in batch.slice(at, 500).columns), strict=True):
                    lines, article = text_lines(source)
                    host, path = _address(url)
                    row = (page_id, url, _key(page_id, url, source), host, path, article, [x for x, _, _ in lines], [b for _, _, b in lines], [r for _, r, _ in lines])
                    for column, v in zip(out, row, strict=True):
                        column.append(v)
                yield pa.RecordBatch.from_arrays([pa.array(c, f.type) for c, f in zip(out, _PARSED_ARROW, strict=True)], schema=_PARSED_ARROW)

    return pages.select(F.col("page_id").cast("long"), "url", "html").mapInArrow(parse, _PARSED)


def shared_lines(parsed: DataFrame) -> DataFrame:
    """(key, article, host, box, n, shared, places): what each page shares with its nearest page, by element.

    ``places`` lists the shared lines of an element.
    Pages that are alone on their host have no rows.  One range-partitioned sort by
    host and path of line hashes.  The first and last page of each partition are
    sent to all tasks, two rows for each partition, so pairs don't depend on where
    partitions end.
    """
    rows = parsed.select("key", "host", "path", "article", F.transform("lines", lambda x: F.xxhash64(x)).alias("hashes"), "boxes", "roles")
    rows = rows.repartitionByRange("host", "path", "key").sortWithinPartitions("host", "path", "key")
    rows = checkpointed(rows)

    def ends(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        first = last = None
        for batch in batches:
            if len(batch):
                first = batch.slice(0, 1) if first is None else first
                last = batch.slice(len(batch) - 1, 1)
        if first is not None:
            part = TaskContext.get().partitionId()
            for side, x in ((0, first), (1, last)):
                yield pa.RecordBatch.from_arrays([pa.array([part], pa.int32()), pa.array([side], pa.int32()), *x.select(["host", "path", "hashes"]).columns], names=["part", "side", "host", "path", "hashes"])

    borders = rows.mapInArrow(ends, "part int, side int, host string, path string, hashes array<long>").collect()
    before, after = {}, {}
    parts = sorted({r["part"] for r in borders})
    by = {(r["part"], r["side"]): (r["host"], r["path"], list(r["hashes"])) for r in borders}
    for p, q in zip(parts, parts[1:], strict=False):
        before[q], after[p] = by[p, 1], by[q, 0]

    def pair(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        part = TaskContext.get().partitionId()
        previous, current = before.get(part), None

        def differ(page: tuple, left: tuple | None, right: tuple | None) -> list[tuple]:
            key, host, path, article, hashes, boxes, roles = page
            near = [x for x in (left, right) if x is not None and x[0] == host]
            if not near:
                return []
            best = max(near, key=lambda x: _common(path, x[1]))
            shared = common_lines(hashes, best[2])
            by_box: dict[int, list] = {}
            for k, (box, role) in enumerate(zip(boxes, roles, strict=True)):
                if role != DROPPED:
                    own = by_box.setdefault(box, [0, 0, []])
                    own[0] += 1
                    if k in shared:
                        own[1] += 1
                        own[2].append(k)
            return [(key, article, host, box, n, m, places) for box, (n, m, places) in by_box.items()]

        for batch in batches:
            found: list[tuple] = []
            for page in zip(*(c.to_pylist() for c in batch.columns), strict=True):
                if current is not None and page[0] == current[0]:
                    continue  # the same page once more
                if current is not None:
                    found += differ(current, previous, (page[1], page[2], page[4]))
                    previous = (current[1], current[2], current[4])
                current = page
            yield as_rows(found)
        if current is not None:
            yield as_rows(differ(current, previous, after.get(part)))

    types = (pa.int64(), pa.bool_(), pa.string(), pa.int64(), pa.int32(), pa.int32(), pa.list_(pa.int32()))

    def as_rows(found: list[tuple]) -> pa.RecordBatch:
        columns = list(zip(*found, strict=True)) or [[]] * len(types)
        return pa.RecordBatch.from_arrays([pa.array(c, t) for c, t in zip(columns, types, strict=True)], names=["key", "article", "host", "box", "n", "shared", "places"])

    return rows.mapInArrow(pair, "key long, article boolean, host string, box long, n int, shared int, places array<int>")


def template_marks(shared: DataFrame, least_share: float = LEAST_SHARE, least_pages: int = LEAST_PAGES) -> DataFrame:
    """(key, marked, places): each page's elements that are template on its host, and its shared lines.

    Only pages where these decide something have a row.  Numbers of elements are counted over all pages
    of a host; a page's row gathers what that one page holds.
    """
    total = shared.groupBy("host", "box").agg(F.sum("n").alias("n"), F.sum("shared").alias("m"), F.count("*").alias("pages"))
    template = total.where((F.col("m") >= least_share * F.col("n")) & (F.col("pages") >= least_pages)).select("host", "box", F.lit(True).alias("template"))
    # A host may hold a third of all pages: its elements are copied, and its pages dealt over the copies.
    copies = template.withColumn("salt", F.explode(F.sequence(F.lit(0), F.lit(_SALTS - 1))))
    salted = shared.withColumn("salt", F.pmod("key", F.lit(_SALTS)).cast("int"))
    marked = salted.join(copies, ["host", "box", "salt"], "left").where("template or size(places) > 0")
    boxes = F.collect_set(F.when(F.col("template"), F.col("box")))
    pages = marked.groupBy("key").agg(F.max("article").alias("article"), boxes.alias("marked"), F.flatten(F.collect_set("places")).alias("places"))
    return pages.where("not article or size(marked) > 0").drop("article")


def main_lines(lines: list[str], roles: list[int], boxes: list[int], article: bool, marked: set[int], places: set[int]) -> list[str]:
    """The lines of a page that are its main text.

    The element with most text of its own stays whatever it shares; where all is
    shared, the pages are copies of each other, and the largest element stays.
    """
    wanted = ARTICLE if article else FREE
    size: dict[int, tuple[int, int]] = {}
    for k, (text, role, box) in enumerate(zip(lines, roles, boxes, strict=True)):
        if role == wanted:
            own, total = size.get(box, (0, 0))
            size[box] = (own + len(text) * (k not in places), total + len(text))
    main = max(size, key=lambda b: size[b]) if size else None
    return [
        text for k, (text, role, box) in enumerate(zip(lines, roles, boxes, strict=True))
        if role == wanted and (box not in marked or box == main) and (article or k not in places)
    ]


def main_text(pages: DataFrame) -> DataFrame:
    """Per row of ``pages``: page_id, url, text, n_chars.

    Null or empty html gives an empty text.  A null url belongs to a host of its
    own.  Rows that are equal in all three columns count as one page when pairs
    are made and all appear in the result.  Other columns are ignored.
    """
    parsed = stored(parsed_pages(pages), "parsed-pages")
    marks = stored(template_marks(stored(shared_lines(parsed), "shared-lines")), "template-marks")
    rows = parsed.select("page_id", "url", "key", "article", "lines", "boxes", "roles")
    if marks.isEmpty():
        rows = rows.withColumn("marked", F.lit(None).cast("array<long>")).withColumn("places", F.lit(None).cast("array<int>"))
    else:
        rows = rows.join(marks, "key", "left")

    def choose(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in batches:
            for at in range(0, len(batch), 500):
                part = batch.slice(at, 500)
                texts = []
                for article, lines, boxes, roles, marked, places in zip(*(part.column(c).to_pylist() for c in ("article", "lines", "boxes", "roles", "marked", "places")), strict=True):
                    texts.append("\n".join(main_lines(lines, roles, boxes, article, set(marked or ()), set(places or ()))))
                yield pa.RecordBatch.from_arrays([part.column("page_id"), part.column("url"), pa.array(texts, pa.string())], names=["page_id", "url", "text"])

    return rows.mapInArrow(choose, "page_id long, url string, text string").withColumn("n_chars", F.length("text").cast("long"))
