"""Operator 5, main text of web pages by differencing with the page of the nearest URL.

1. Each page is cut into text lines (blocks) by one pass over its tags. Each line is marked: protected, when it stands inside an article or
   main element and in no part that is never content; refused, when it stands in a menu, header, footer, sidebar, notice, advert,
   form, script, style, comment section or hidden element; or open.
2. The pages of a host are sorted by URL path, page_id and a digest of their lines. Of the nearest pages before and after that differ in their lines, the one
   whose path shares the longer beginning is a page's partner (the one before, if equal). All lines of both are aligned by a longest common
   subsequence; lines that both have are template.
3. Tags are asked after that, and may confirm or veto. An article's text is the page's own, though another page may quote it: protected lines stay, and
   a page that has any keeps these alone. Refused lines go, shared or not, as adverts and comments change from page to page. Open lines go if shared.

The order is cut into contiguous ranges, so the result does not hang on how large a host is or how pages are spread:
* A first scan makes the keys (host, path, page_id, digest). They are sorted into ranges of about PART_BYTES of html, at most MAX_PARTS, and each range is
  summed up by its first and last page and the first and last that differ from these.
* From these summaries the driver works out which pages, at most four a range, a range must see of the ranges beside it.
* A second scan deals the lines to the ranges, the edge pages to two. A task holds three different pages and the keys of a run of equal ones.

Defined cases: null or empty html has empty text. A null url makes a page of the host "" with an empty path. Pages without a
partner keep their open lines. Repeated rows are each returned; equal pages are no partners of each other, however many there are. Of equal paths
the order is by page_id (null first), then digest. Empty tables give no rows. Other columns are not read. The whole html is read, however
long; unclosed and unknown tags are accepted.
"""

from __future__ import annotations

import hashlib
import html as entities
import re
from bisect import bisect_left, bisect_right
from collections import defaultdict
from urllib.parse import urlsplit

import pyarrow as pa
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from .common import drop_stored, lean, pieces, stored, table

PART_BYTES, MAX_PARTS = 1 << 24, 50_000

#: HTML's elements by what they do to text.
RAW = frozenset("script style template noscript iframe svg math object audio video canvas textarea title noframes".split())
REFUSED = frozenset("head nav header footer aside form button select dialog menu".split())
VOID = frozenset("area base br col embed hr img input link meta param source track wbr".split())
BLOCK = frozenset(
    "address article aside blockquote body br caption center dd details dialog dir div dl dt fieldset figcaption figure footer form h1 h2 h3 h4 h5 h6 head header hr html legend li main menu nav ol option optgroup p pre "
    "section summary table tbody td tfoot th thead tr ul".split()
)
CLOSES_P = BLOCK - frozenset(["br", "option", "optgroup", "html", "body", "head", "td", "th", "tr", "caption"])
CONTENT = frozenset(["article", "main"])
SIBLINGS = {"li": ("li",), "dt": ("dt", "dd"), "dd": ("dt", "dd"), "tr": ("tr", "td", "th"), "td": ("td", "th"), "th": ("td", "th"), "option": ("option",)}
ROLES = frozenset("navigation banner contentinfo complementary search form menu menubar dialog alertdialog".split())
#: Words in class or id that mark a part that is never content.
NAMES = re.compile(
    r"(?:^|[\s_-])(?:ads?|advert\w*|sponsor\w*|promo\w*|banner|nav\w*|menu|breadcrumbs?|sidebar|side-bar|footer|masthead|cookies?|consent|gdpr|notices?|alert|popup|modal|overlay|newsletter|subscribe|signup|login|social|share|sharing"
    r"|related|recommend\w*|comments?|comment-?list|replies|disqus|respond|pagination|pager|toolbar|widget|skip-link|copyright)(?:$|[\s_-])",
    re.I,
)
_TOKEN = re.compile(r"""<!--.*?(?:-->|\Z)|<[!?][^>]*(?:>|\Z)|<(/?)([a-zA-Z][^\s/>]*)((?:[^>"']|"[^"]*"|'[^']*')*)(?:>|\Z)""", re.S)
_ATTR = re.compile(r"""([^\s=/"'<>]+)(?:\s*=\s*(?:"([^"]*)"|'([^']*)'|([^\s>]+)))?""")
PROTECTED, OPEN, DROPPED = 2, 1, 0


def _refused(tag: str, attrs: str, inside: bool) -> bool:
    """A header inside an article is the article's own."""
    if tag in REFUSED and not (tag == "header" and inside):
        return True
    if not attrs or tag in ("html", "body"):
        return False
    found = {m[1].lower(): next((x for x in m.groups()[1:] if x is not None), "") for m in _ATTR.finditer(attrs)}
    if "hidden" in found or found.get("aria-hidden", "").lower() == "true" or found.get("role", "").lower() in ROLES:
        return True
    if re.search(r"display\s*:\s*none|visibility\s*:\s*hidden", found.get("style", ""), re.I):
        return True
    return tag not in CONTENT and any(NAMES.search(found.get(k, "")) for k in ("class", "id"))


def page_lines(page: str) -> list[tuple[str, int]]:
    """Text lines of a page with their marks, in page order."""
    out: list[tuple[str, int]] = []
    parts: list[str] = []
    stack: list[tuple[str, bool, bool]] = []  # tag, whether it is refused, whether it holds content
    refused = content = at = 0
    size = len(page)

    def flush() -> None:
        if parts:
            text = " ".join(entities.unescape("".join(parts)).split())
            parts.clear()
            if text:
                out.append((text, DROPPED if refused else PROTECTED if content else OPEN))

    def pop(k: int) -> None:
        nonlocal refused, content
        for _, r, c in stack[k:]:
            refused -= r
            content -= c
        del stack[k:]

    def last(tags: tuple[str, ...], stop: frozenset) -> int:
        for k in range(len(stack) - 1, -1, -1):
            if stack[k][0] in tags:
                return k
            if stack[k][0] in stop:
                break
        return -1

    while at < size:
        m = _TOKEN.search(page, at)
        if m is None:
            parts.append(page[at:])
            break
        if m.start() > at:
            parts.append(page[at : m.start()])
        at = m.end()
        if m[2] is None:
            continue
        tag = m[2].lower()
        if m[1]:
            if tag in BLOCK:
                flush()
            k = last((tag,), frozenset(["html"]))
            if k >= 0:
                pop(k)
            continue
        attrs = m[3] or ""
        if tag in RAW:
            if not attrs.endswith("/"):
                end = re.compile(rf"</{re.escape(tag)}\s*>", re.I).search(page, at)
                at = end.end() if end else size
            continue
        if tag in BLOCK:
            flush()
            if tag in CLOSES_P and (k := last(("p",), frozenset(["table", "td", "th", "button"]))) >= 0:
                pop(k)
            if tag in SIBLINGS and (k := last(SIBLINGS[tag], frozenset(["ul", "ol", "dl", "table", "select"]))) >= 0:
                pop(k)
        if tag in VOID or attrs.endswith("/") and tag not in BLOCK:
            continue
        bad = _refused(tag, attrs, content > 0)
        good = tag in CONTENT or 'role="main"' in attrs
        stack.append((tag, bad, good))
        refused += bad
        content += good
    flush()
    return out


def common_lines(a: list[str], b: list[str]) -> set[int]:
    """Places in a of a longest common subsequence of a and b: equal ends, and between them the longest rising run of matching places."""
    head, end = 0, min(len(a), len(b))
    while head < end and a[head] == b[head]:
        head += 1
    tail = 0
    while tail < end - head and a[-1 - tail] == b[-1 - tail]:
        tail += 1
    places: dict[str, list[int]] = {}
    for j in range(head, len(b) - tail):
        places.setdefault(b[j], []).append(j)
    ends: list[int] = []
    links: list[tuple] = []
    for i in range(head, len(a) - tail):
        for j in reversed(places.get(a[i], ())):
            k = bisect_left(ends, j)
            link = (i, links[k - 1] if k else None)
            if k == len(ends):
                ends.append(j)
                links.append(link)
            else:
                ends[k] = j
                links[k] = link
    found, link = {*range(head), *range(len(a) - tail, len(a))}, links[-1] if links else None
    while link is not None:
        found.add(link[0])
        link = link[1]
    return found


def main_text(lines: list[str], marks: bytes, partner: list[str] | None) -> tuple[str, int, int]:
    """The text, how many lines are shared with the partner, and how many of these the tags keep."""
    shared = common_lines(lines, partner) if partner is not None else set()
    vetoed = sum(marks[i] == PROTECTED for i in shared)
    if PROTECTED in marks:
        kept = (x for x, m in zip(lines, marks, strict=True) if m == PROTECTED)
    else:
        kept = (x for i, (x, m) in enumerate(zip(lines, marks, strict=True)) if i not in shared and m == OPEN)
    return "\n".join(kept), len(shared), vetoed


def host_path(url: str | None) -> tuple[str, str]:
    try:
        parts = urlsplit((url or "").strip())
        return (parts.hostname or "").lower(), parts.path + (f"?{parts.query}" if parts.query else "")
    except ValueError:
        return "", (url or "").strip()


#: host, path, whether page_id is there, page_id, digest: the order of the pages.
Key = tuple[bytes, bytes, bool, int, bytes]
_KEY = "host string, path string, page_id long, digest binary"
ORDER = ["host", "path", "page_id", "digest"]


def key_of(host: str, path: str, page_id: int | None, digest: bytes) -> Key:
    """Compares as the columns are sorted: strings by their bytes."""
    return host.encode(), path.encode(), page_id is not None, page_id or 0, digest


def _cut(page: str | None) -> tuple[list[str], bytes, bytes]:
    found = page_lines(page or "")
    lines, marks = [t for t, _ in found], bytes(m for _, m in found)
    return lines, marks, hashlib.blake2b("\n".join(lines).encode() + b"\0" + marks, digest_size=12).digest()


def _keys(batches):
    schema = pa.schema([("host", pa.string()), ("path", pa.string()), ("page_id", pa.int64()), ("digest", pa.binary()), ("size", pa.int64())])
    for batch in pieces(batches):
        where = [host_path(u) for u in batch.column("url").to_pylist()]
        html = batch.column("html").to_pylist()
        yield pa.record_batch([pa.array([h for h, _ in where], pa.string()), pa.array([p for _, p in where], pa.string()), batch.column("page_id"), pa.array([_cut(h)[2] for h in html], pa.binary()), pa.array([len(h or "") for h in html], pa.int64())], schema=schema)


def _summary(batches):
    """Of a sorted range: its first and last page and the first and last that differ from these, as host, path, page_id and digest each."""
    found: list = [None] * 4
    for batch in pieces(batches, 4096):
        for row in zip(*(batch.column(c).to_pylist() for c in ORDER), strict=True):
            if found[0] is None:
                found[0] = found[3] = row
            if found[1] is None and row[3] != found[0][3]:
                found[1] = row
            if row[3] != found[3][3]:
                found[2] = found[3]
            found[3] = row
    if found[0] is not None:
        kinds = (pa.string(), pa.string(), pa.int64(), pa.binary())
        yield pa.record_batch([pa.array([None if r is None else r[i]], t) for r in found for i, t in enumerate(kinds)], names=[f"{c}{k}" for k in range(4) for c in ORDER])


def seen_beside(ranges: list[list[Key | None]]) -> dict[Key, list[int]]:
    """For each page that ranges beside its own must see, these ranges. ranges: first, first that differs from it, last that differs from the last, last. A
    range needs the page next to it and the nearest that differs from that, of its own host."""
    out: dict[Key, list[int]] = defaultdict(list)
    for k, own in enumerate(ranges):
        for step, edge, far, near in ((-1, 0, 2, 3), (1, 3, 1, 0)):
            host, at, one = own[edge][0], k + step, None
            while 0 <= at < len(ranges):
                page, other = ranges[at][near], ranges[at][far]
                if page[0] != host:
                    break
                if one is None:
                    one = page
                    out[page].append(k)
                    page = other
                elif page[4] == one[4]:
                    page = other
                if page is not None and page[4] != one[4]:
                    if page[0] == host:
                        out[page].append(k)
                    break
                at += step
    return dict(out)


_DEALT = f"part int, own boolean, url string, {_KEY}, lines array<string>, marks binary"


def _deal(plan):
    """Each page to its range, and to those that must see it."""
    schema = pa.schema([("part", pa.int32()), ("own", pa.bool_()), ("url", pa.string()), ("host", pa.string()), ("path", pa.string()), ("page_id", pa.int64()), ("digest", pa.binary()), ("lines", pa.list_(pa.string())), ("marks", pa.binary())])

    def run(batches):
        firsts, beside = plan.value
        for batch in pieces(batches):
            out = []
            for page_id, url, page in zip(*(batch.column(c).to_pylist() for c in ("page_id", "url", "html")), strict=True):
                host, path = host_path(url)
                lines, marks, digest = _cut(page)
                key = key_of(host, path, page_id, digest)
                own = max(0, bisect_right(firsts, key) - 1)
                for part in (own, *beside.get(key, ())):
                    out.append((part, part == own, url, host, path, page_id, digest, lines, marks))
            yield pa.record_batch([pa.array([r[i] for r in out], f.type) for i, f in enumerate(schema)], schema=schema)

    return run


def _beginning(a: str, b: str) -> int:
    n = 0
    for x, y in zip(a, b):  # noqa: B905
        if x != y:
            break
        n += 1
    return n


def _pair(batches):
    """Rows sorted by range and key. Pages of equal lines that follow one another are a run, between the different pages of the same host before and after."""
    schema = pa.schema([("page_id", pa.int64()), ("url", pa.string()), ("text", pa.string()), ("n_shared", pa.int64()), ("n_vetoed", pa.int64())])
    before = run = None  # run: part, host, digest, lines, marks, members of the range, path of its last page, of its first
    done: list[tuple] = []

    def close(after):
        """The run's rows; before and after are runs that may be partners."""
        part, host, _, lines, marks, members, *_ = run
        texts: dict[int, tuple] = {}
        # of equal distance in order: the last page of the run before, the first of the run after
        near = [x for x in (before, after) if x is not None and x[:2] == [part, host]]
        paths = [x[6] if x is before else x[7] for x in near]
        for page_id, url, path in members:
            k = max(range(len(near)), key=lambda i: _beginning(paths[i], path)) if near else -1
            if k not in texts:
                texts[k] = main_text(lines, marks, near[k][3] if near else None)
            yield (page_id, url, *texts[k])

    def rows():
        nonlocal before, run
        for batch in pieces(batches):
            for part, own, url, host, path, page_id, digest, lines, marks in zip(*(batch.column(c).to_pylist() for c in ("part", "own", "url", "host", "path", "page_id", "digest", "lines", "marks")), strict=True):
                if run is None or run[:3] != [part, host, digest]:
                    new = [part, host, digest, lines, marks, [], path, path]
                    if run is not None:
                        yield from close(new)
                    before, run = run, new
                if own:
                    run[5].append((page_id, url, path))
                run[6] = path
        if run is not None:
            yield from close(None)

    for row in rows():
        done.append(row)
        if len(done) >= 500:
            yield pa.record_batch([pa.array([x[i] for x in done], f.type) for i, f in enumerate(schema)], schema=schema)
            done = []
    if done:
        yield pa.record_batch([pa.array([x[i] for x in done], f.type) for i, f in enumerate(schema)], schema=schema)


def extract_main_text(pages: DataFrame, part_bytes: int = PART_BYTES) -> DataFrame:
    """page_id, url, text, n_chars, n_shared (lines that the page shares with its partner), n_vetoed (those of them that the tags keep). pages: page_id, url, html."""
    spark = pages.sparkSession
    pages = pages.select(F.col("page_id").cast("long"), F.col("url").cast("string"), F.col("html").cast("string"))
    keys = stored(pages.mapInArrow(lean(_keys), f"{_KEY}, size long"), "keys")
    parts = min(MAX_PARTS, max(1, -(-(keys.agg(F.sum("size")).first()[0] or 0) // part_bytes)))
    ranged = keys.drop("size").repartitionByRange(parts, *ORDER).sortWithinPartitions(*ORDER)
    ddl = ", ".join(f"host{k} string, path{k} string, page_id{k} long, digest{k} binary" for k in range(4))
    # fewer keys a range are sampled for the cuts than the default's 100, as all samples meet in the driver
    sample = "spark.sql.execution.rangeExchange.sampleSizePerPartition"
    default = spark.conf.get(sample)
    spark.conf.set(sample, "20")
    try:
        found = ranged.mapInArrow(lean(_summary), ddl).collect()
    finally:
        spark.conf.set(sample, default)
    rows = [[None if r[f"digest{k}"] is None else key_of(r[f"host{k}"], r[f"path{k}"], r[f"page_id{k}"], bytes(r[f"digest{k}"])) for k in range(4)] for r in found]
    rows.sort(key=lambda r: r[0])
    drop_stored(keys)
    plan = spark.sparkContext.broadcast(([r[0] for r in rows], seen_beside(rows)))
    dealt = pages.mapInArrow(lean(_deal(plan)), _DEALT).repartitionById(max(1, len(rows)), F.col("part")).sortWithinPartitions("part", *ORDER)
    text = dealt.mapInArrow(lean(_pair), "page_id long, url string, text string, n_shared long, n_vetoed long")
    return text.select("page_id", "url", "text", F.length("text").cast("long").alias("n_chars"), "n_shared", "n_vetoed")


def op5_html_extract(spark: SparkSession, sf_dir: str) -> DataFrame:
    return extract_main_text(table(spark, sf_dir, "pages"))
