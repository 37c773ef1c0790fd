"""Main text of web pages by differencing each page with its nearest page by URL.

A page becomes its text blocks in order, each with its place: the chain of elements and classes
that it stands in. Pages are put in the order of host and path, and each is paired with the page near
it on its host whose path shares the longest beginning. Blocks of the two are aligned by a longest
common subsequence over (place, text), and those that both pages share are the site's template and are
deleted. Copies are no partners: equal pages of a host are one page here, and a page that shares
half of this one's prose is passed over for the next nearest, so an article is never deleted
because it was published twice.

A second rule goes by what elements say they are: menus, forms, adverts, comments and the like are
never text, and the blocks of a page's own ``article`` or ``main`` are always kept. ``n_template`` counts
the blocks that differencing deletes, ``n_declared`` those that the second rule alone deletes.
"""

from __future__ import annotations

import hashlib
import html
import re
import zlib
from collections import Counter
from collections.abc import Iterator
from os.path import commonprefix
from typing import NamedTuple

import numpy as np
import pyarrow as pa
from pyspark import TaskContext
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import Window as W
from pyspark.sql import functions as F

from corpus_audit.llm.common import BROADCAST_ROWS, discard, materialize, whole_text

#: Each alternative fails within the tag that it is tried on: a tag ends before the next "<" outside quotes, or at the first ">".
_TAG = re.compile(
    r"<!--.*?(?:-->|\Z)|<!\[CDATA\[.*?(?:\]\]>|\Z)|<[!?][^>]*+>"
    r"|<(?P<end>/?)(?P<name>[A-Za-z][A-Za-z0-9:-]*+)(?P<attrs>(?:[^<>=]++|=\s*+(?:\"[^\"]*+\"|'[^']*+')?+)*+)>"
    r"|<(?P<end2>/?)(?P<name2>[A-Za-z][A-Za-z0-9:-]*+)(?P<attrs2>[^>]*+)>",
    re.S,
)
_ATTR = re.compile(r"(class|id|role|hidden|aria-hidden)\s*(?:=\s*(?:\"([^\"]*)\"|'([^']*)'|([^\s>]+)))?", re.I)
_CLASS = re.compile(r"\bclass\s*=\s*(?:\"[^\"]*\"|'[^']*'|[^\s>]+)", re.I)
#: Element names and name parts of classes and ids.
_RAW = frozenset("script style noscript template iframe title textarea xmp noembed select button".split())
_VOID = frozenset("area base br col embed hr img input link meta param source track wbr".split())
_BLOCK = frozenset("address article aside blockquote body caption center dd details dialog div dl dt fieldset figcaption figure footer form h1 h2 h3 h4 h5 h6 head header hgroup hr html legend li main menu nav ol option p pre search section summary table tbody td tfoot th thead tr ul".split())
_ENDS_P = _BLOCK - frozenset("body caption head html legend option tbody td tfoot th thead tr".split())
_SCOPE = frozenset("caption html table td th".split())
_NEVER = frozenset("head nav aside footer form menu dialog".split())
_MAIN = frozenset(["article", "main"])
_NEVER_PARTS = frozenset("ad ads advert adverts advertisement advertising adsense sponsor sponsored promo promotion banner comment comments commentlist respond replies disqus sidebar menu nav navbar navigation breadcrumb breadcrumbs notice notices cookie cookies consent gdpr popup modal overlay newsletter subscribe share sharing social related widget toolbar pagination pager".split())
_OUTER_PARTS = frozenset("header footer masthead topbar".split())
_NEVER_ROLES = frozenset("navigation banner contentinfo complementary search dialog alert alertdialog menu menubar".split())
PLAIN, KEPT, NEVER = 0, 1, 2
#: Words from which a block is prose; a page with most of another's prose is a copy of it.
PROSE_WORDS = 20
#: Pages on each side among which the partner is looked for.
NEAR = 8
#: Pages of one stretch of the order that are differenced together.
STRETCH = 2048


def _zone(name: str, attrs: str, zone: int) -> int:
    """Zone of an element opened inside ``zone``."""
    if zone == NEVER or name in _NEVER:
        return NEVER
    if name == "header" and zone != KEPT:
        return NEVER
    if attrs and name not in ("html", "body"):
        for m in _ATTR.finditer(attrs):
            key, value = m[1].lower(), (m[2] or m[3] or m[4] or "").lower()
            if key == "hidden" or key == "aria-hidden" and value == "true" or key == "role" and value in _NEVER_ROLES:
                return NEVER
            if key in ("class", "id"):
                parts = set(re.split(r"[^a-z0-9]+", value))
                if parts & _NEVER_PARTS or zone != KEPT and name not in _MAIN and parts & _OUTER_PARTS:
                    return NEVER
    return KEPT if name in _MAIN else zone


class _Open(NamedTuple):
    """An open element: its zone, the hash of its chain of elements, and the number of the open paragraph that a block would end."""

    name: str
    zone: int
    place: int
    paragraph: int


_ROOT = _Open("", PLAIN, 0, -1)


def blocks(page: str) -> list[tuple[str, int, int]]:
    """(text, zone, place) of the non-empty blocks in page order; character references are decoded. One pass, whatever the nesting."""
    out: list[tuple[str, int, int]] = []
    stack: list[_Open] = [_ROOT]
    open_: Counter = Counter()
    held: list[str] = []
    at, last = 0, page.rfind(">")

    def flush() -> None:
        if held:
            text = " ".join(html.unescape("".join(held)).split())
            if text:
                out.append((text, stack[-1].zone, stack[-1].place))
            held.clear()

    def close(k: int) -> None:
        for x in stack[k:]:
            open_[x.name] -= 1
        del stack[k:]

    while at <= last and (m := _TAG.search(page, at)):
        if m.start() > at:
            held.append(page[at : m.start()])
        at = m.end()
        name = (m["name"] or m["name2"] or "").lower()
        if not name:
            continue
        if name == "br":
            held.append(" ")
            continue
        if name in _BLOCK:
            flush()
        if m["end"] or m["end2"]:
            if open_[name]:
                k = len(stack) - 1
                while stack[k].name != name:
                    k -= 1
                if any(x.zone != stack[k - 1].zone for x in stack[k:]):
                    flush()
                close(k)
        elif name in _RAW:
            stop = re.compile(rf"</{re.escape(name)}\b[^>]*>", re.I).search(page, at)
            at = stop.end() if stop else len(page)
        elif name not in _VOID:
            if name in _ENDS_P and stack[-1].paragraph >= 0:  # a block that begins ends an open paragraph, with what is open inside it
                close(stack[-1].paragraph)
            attrs, top = m["attrs"] or m["attrs2"] or "", stack[-1]
            zone = _zone(name, attrs, top.zone)
            if zone != top.zone:
                flush()
            label = _CLASS.search(attrs) if attrs else None
            place = zlib.crc32(f"{name}.{label[0].lower() if label else ''}".encode("utf-8", "replace"), top.place) if name in _BLOCK or zone != top.zone else top.place
            stack.append(_Open(name, zone, place, -1 if name in _SCOPE else len(stack) if name == "p" else top.paragraph))
            open_[name] += 1
    held.append(page[at:])
    flush()
    return out


def _block_hash(text: str, place: int) -> int:
    return int.from_bytes(hashlib.blake2b(f"{place}\x00{text}".encode("utf-8", "surrogatepass"), digest_size=8).digest(), "little", signed=True)


def _rows(a: list[int], b: list[int]) -> Iterator[int]:
    """Bit-parallel rows: a zero at bit j says that b[j] makes the common subsequence with a's beginning longer."""
    where: dict[int, int] = {}
    for j, x in enumerate(b):
        where[x] = where.get(x, 0) | 1 << j
    full = row = (1 << len(b)) - 1
    for x in a:
        hit = row & where.get(x, 0)
        row = ((row + hit) | (row - hit)) & full
        yield row


def _lengths(a: list[int], b: list[int]) -> np.ndarray:
    """Length of the longest common subsequence of ``a`` with each beginning of ``b``."""
    row = (1 << len(b)) - 1
    for row in _rows(a, b):  # noqa: B007
        pass
    bits = np.unpackbits(np.frombuffer(row.to_bytes(len(b) // 8 + 1, "little"), dtype=np.uint8), bitorder="little")[: len(b)]
    return np.concatenate([[0], np.cumsum(1 - bits.astype(np.int64))])


def _walk(a: list[int], b: list[int]) -> list[int]:
    rows = list(_rows(a, b))
    found, i, j = [], len(a), len(b)
    while i and j:
        if rows[i - 1] >> (j - 1) & 1:  # column j adds nothing to row i
            j -= 1
        elif i > 1 and not rows[i - 2] >> (j - 1) & 1:  # row i adds nothing
            i -= 1
        else:
            found.append(i - 1)
            i, j = i - 1, j - 1
    return found[::-1]


def shared_blocks(a: list[int], b: list[int], room: int = 1 << 24) -> list[int]:
    """Positions of ``a`` on a longest common subsequence with ``b``.

    Equal ends and blocks that the other page lacks are taken out first. What would need more than ``room`` bits of rows is
    halved at the point where both halves' lengths add up best.
    """
    head = 0
    while head < min(len(a), len(b)) and a[head] == b[head]:
        head += 1
    tail = 0
    while tail < min(len(a), len(b)) - head and a[-1 - tail] == b[-1 - tail]:
        tail += 1
    mid_a, mid_b = a[head : len(a) - tail], b[head : len(b) - tail]
    in_a, in_b = set(mid_a), set(mid_b)
    at = [i for i, x in enumerate(mid_a) if x in in_b]
    x, y = [mid_a[i] for i in at], [v for v in mid_b if v in in_a]

    def solve(x: list[int], y: list[int]) -> list[int]:
        if not x or not y:
            return []
        if len(x) == 1 or len(x) * len(y) <= room:
            return _walk(x, y)
        half = len(x) // 2
        both = _lengths(x[:half], y) + _lengths(x[half:][::-1], y[::-1])[::-1]
        cut = int(both.argmax())
        return solve(x[:half], y[:cut]) + [half + i for i in solve(x[half:], y[cut:])]

    return [*range(head), *(head + at[i] for i in solve(x, y)), *range(len(a) - tail, len(a))]


def _outline(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
    """A page's block hashes, those of its prose, the numbers of those declared to be no text, and one hash of all."""
    for batch in batches:
        hashes, prose, never, whole = [], [], [], []
        for x in batch.column("html"):
            found = [(t, _block_hash(t, p), z) for t, z, p in blocks(x.as_py())]
            hashes.append([h for _, h, _ in found])
            # Prose is told by its text alone: a copy may stand elsewhere in its page.
            prose.append(sorted({_block_hash(t, 0) for t, _, z in found if z != NEVER and t.count(" ") + 1 >= PROSE_WORDS}))
            never.append([k for k, (_, _, z) in enumerate(found) if z == NEVER])
            whole.append(hashlib.blake2b(np.asarray(hashes[-1], dtype=np.int64).tobytes(), digest_size=16).digest())
        columns = [*(batch.column(c) for c in ("pid", "hh", "host", "path")), *(pa.array(x, type=pa.list_(pa.int64())) for x in (hashes, prose, never)), pa.array(whole, type=pa.binary())]
        yield pa.RecordBatch.from_arrays(columns, names=["pid", "hh", "host", "path", "blocks", "prose", "never", "whole"])


def _number(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
    """Partition and place in it of each row."""
    part, n = TaskContext.get().partitionId(), 0
    for batch in batches:
        k = batch.num_rows
        yield pa.RecordBatch.from_arrays([*batch.columns, pa.array([part] * k, type=pa.int32()), pa.array(range(n, n + k), type=pa.int64())], names=[*batch.schema.names, "part", "idx"])
        n += k


class _Page(NamedTuple):
    host: str
    path: str
    whole: bytes
    blocks: list[int]
    prose: set[int]
    never: set[int]
    rank: int
    own: bool


def strangers(page: _Page, near: list[_Page]) -> list[_Page]:
    """The pages of its host that are no copies of it."""
    return [x for x in near if x.host == page.host and x.whole != page.whole and 2 * len(page.prose & x.prose) < max(1, min(len(page.prose), len(x.prose)))]


def template_of(page: _Page, near: list[_Page]) -> list[int]:
    """Numbers of the blocks that the page shares with its partner and, unless they are declared to be no text, with most of the strangers near it.

    The partner is the stranger whose path shares the longest beginning, then the nearer one, then the earlier one.
    A line that two articles of a site have in common, such as a licence, is not in most of its pages.
    """
    others = strangers(page, near)
    if not others:
        return []
    best = max(others, key=lambda x: (len(commonprefix([x.path, page.path])), -abs(x.rank - page.rank), -x.rank))
    shared = shared_blocks(page.blocks, best.blocks)
    held = Counter(h for x in others for h in set(x.blocks)) if shared else {}
    return [k for k in shared if k in page.never or 2 * held[page.blocks[k]] > len(others)]


def _difference(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
    """``host, whole, gone`` of each stretch's own pages, which come in order with NEAR more on both sides."""
    window: list[_Page] = []
    stretch, done = None, 0

    def settle(upto: int) -> list[tuple[str, bytes, list[int]]]:
        nonlocal done
        out = []
        while done < upto:
            page = window[done]
            gone = template_of(page, window[max(0, done - NEAR) : done] + window[done + 1 : done + 1 + NEAR]) if page.own else []
            if gone:
                out.append((page.host, page.whole, gone))
            done += 1
        drop = max(0, done - NEAR)
        del window[:drop]
        done -= drop
        return out

    def packed(rows: list[tuple]) -> pa.RecordBatch:
        host, whole, gone = zip(*rows, strict=True) if rows else ((), (), ())
        return pa.RecordBatch.from_arrays([pa.array(host, type=pa.string()), pa.array(whole, type=pa.binary()), pa.array(gone, type=pa.list_(pa.int32()))], names=["host", "whole", "gone"])

    for batch in batches:
        rows = []
        for r in batch.to_pylist():
            if r["stretch"] != stretch:
                rows += settle(len(window))
                window.clear()
                stretch, done = r["stretch"], 0
            window.append(_Page(r["host"], r["path"], r["whole"], r["blocks"], set(r["prose"]), set(r["never"]), r["rank"], r["rank"] // STRETCH == stretch))
            rows += settle(len(window) - NEAR)
        yield packed(rows)
    yield packed(settle(len(window)))


def template_blocks(pages: DataFrame) -> DataFrame:
    """``pid, hh, gone``: for pages that share blocks with their partner, the numbers of those blocks.

    Pages without a host have no partner.
    """
    url = F.col("url")
    path = F.concat_ws("?", F.coalesce(F.try_parse_url(url, F.lit("PATH")), F.lit("")), F.try_parse_url(url, F.lit("QUERY")))
    slim = pages.select(
        F.coalesce(F.col("page_id").cast("long"), F.lit(-1)).alias("pid"), F.xxhash64(whole_text("html")).alias("hh"),
        F.lower(F.try_parse_url(url, F.lit("HOST"))).alias("host"), path.alias("path"), whole_text("html").alias("html"),
    )
    shape = "pid long, hh long, host string, path string, blocks array<long>, prose array<long>, never array<long>, whole binary"
    outlines = materialize(slim.mapInArrow(_outline, shape).filter(F.col("host").isNotNull() & (F.size("blocks") > 0)), "outlines")
    # Equal pages of a host are one; its path is their lowest.
    single = outlines.groupBy("host", "whole").agg(F.min("path").alias("path"), F.first("blocks").alias("blocks"), F.first("prose").alias("prose"), F.first("never").alias("never"))
    n = int(pages.sparkSession.conf.get("spark.sql.shuffle.partitions"))
    order = ["host", "path", "whole"]
    numbered = single.select("host", "path", "whole", "blocks", "prose", "never").repartitionByRange(n, *order).sortWithinPartitions(*order).mapInArrow(_number, "host string, path string, whole binary, blocks array<long>, prose array<long>, never array<long>, part int, idx long")
    ordered = materialize(numbered, "ordered")
    # One row for each partition: the number of pages before it.
    sizes = ordered.groupBy("part").agg(F.max("idx").alias("last")).select("part", (F.sum(F.col("last") + 1).over(W.orderBy("part")) - F.col("last") - 1).alias("before"))
    ranked = ordered.join(F.broadcast(sizes), "part").withColumn("rank", F.col("before") + F.col("idx"))
    around = F.array_distinct(F.transform(F.array(F.col("rank") - NEAR, F.col("rank"), F.col("rank") + NEAR), lambda r: F.floor(F.greatest(F.lit(0), r) / STRETCH)))
    dealt = ranked.select("host", "path", "whole", "blocks", "prose", "never", "rank", F.explode(around).alias("stretch"))
    shared = dealt.repartition("stretch").sortWithinPartitions("stretch", "rank").mapInArrow(_difference, "host string, whole binary, gone array<int>")
    found = materialize(shared, "shared")
    gone = materialize(outlines.select("pid", "hh", "host", "whole").distinct().join(found, ["host", "whole"]).groupBy("pid", "hh").agg(F.first("gone").alias("gone")), "template")
    discard(outlines, ordered, found)
    return gone


def extract(pages: DataFrame) -> DataFrame:
    """``page_id, url, text, n_chars, n_template, n_declared`` for every page.

    Null and empty html give the empty text, pages of any length and nesting are read whole, rows that repeat
    (page_id, html) get the same text, ties between partners go to the nearer page and then the earlier one, an empty
    table gives an empty result, and other columns are not read.
    """
    gone = template_blocks(pages)
    size = gone.agg(F.count("*"), F.coalesce(F.sum(F.size("gone")), F.lit(0))).first()
    if size[0] <= BROADCAST_ROWS // 4 and size[1] <= 2 * BROADCAST_ROWS:
        gone = F.broadcast(gone)
    keyed = pages.select("page_id", "url", whole_text("html").alias("html"), F.coalesce(F.col("page_id").cast("long"), F.lit(-1)).alias("__pid"), F.xxhash64(whole_text("html")).alias("__hh"))
    joined = keyed.join(gone, (F.col("__pid") == F.col("pid")) & (F.col("__hh") == F.col("hh")), "left").select("page_id", "url", "html", "gone")

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in batches:
            texts, template, declared = [], [], []
            for page, gone in zip(batch.column("html"), batch.column("gone"), strict=True):
                drop, kept, by_diff, by_name = set(gone.as_py() or ()), [], 0, 0
                for k, (text, zone, _) in enumerate(blocks(page.as_py())):
                    if zone != KEPT and k in drop:
                        by_diff += 1
                    elif zone == NEVER:
                        by_name += 1
                    else:
                        kept.append(text)
                texts.append("\n".join(kept))
                template.append(by_diff)
                declared.append(by_name)
            counts = (pa.array(x, type=pa.int64()) for x in ([len(t) for t in texts], template, declared))
            yield pa.RecordBatch.from_arrays([batch.column("page_id"), batch.column("url"), pa.array(texts, type=pa.string()), *counts], names=["page_id", "url", "text", "n_chars", "n_template", "n_declared"])

    kinds = dict(pages.dtypes)
    return joined.mapInArrow(run, f"page_id {kinds['page_id']}, url {kinds['url']}, text string, n_chars long, n_template long, n_declared long")


def op5_extraction(spark: SparkSession, sf_dir: str) -> DataFrame:
    """The main text of every page; see ``extract`` for odd rows."""
    return extract(spark.read.parquet(f"{sf_dir}/pages.parquet").select("page_id", "url", "html"))
