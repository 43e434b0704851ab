"""Main text of web pages: differencing of each page against the page of its host nearest by URL, then structure.

The pages of a host are ordered by URL path; a page's partner is the neighbour in that order whose path has more leading
segments in common with its own (the one before, if both have as many). Pages of a host with the same lines count as one, so a
partner always differs. The text lines of both are aligned by longest common subsequence: what they share is template
text and is deleted. Two rules follow, for what differencing can't tell. A line that both pages show inside an element that declares
itself the article is a paragraph of both, and stays. A line that differs but stands in an element that declares itself
something else (an advert that changes from page to page), or outside the article of a page that declares one, goes.

Only hashes of lines travel to the partners; the order is a global rank, so the number of partitions changes nothing.

Defined results: null or empty html gives an empty text. A page without another page on its host, or with copies of itself only, has no
partner and loses nothing to differencing. A null URL is a host of its own. Rows of equal id are pages of their own.
"""

from __future__ import annotations

import html as entities
import re
from collections.abc import Iterator

import numpy as np
import pyarrow as pa
import xxhash
import zstandard
from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

from .common import materialize, ranked

#: Elements whose content is no line of the page.
HIDDEN = frozenset("script style noscript template head title select option textarea input iframe svg canvas object".split())
#: Elements that declare themselves something else than the article.
ASIDE = frozenset("nav footer aside form button menu dialog".split())
#: Words in class, id or role that declare an element something else than the article.
BOILERPLATE_WORDS = frozenset(
    "ad ads adv advert adverts advertisement advertising sponsored sponsor promo promotion banner cookie cookies consent notice notices gdpr "
    "nav navbar navigation menu menubar breadcrumb breadcrumbs pagination pager sidebar aside rail widget widgets related recommended "
    "recommendations share sharing social footer masthead topbar header newsletter subscribe signup login popup modal overlay comment "
    "comments commentlist disqus replies reactions search complementary contentinfo alert".split()
)
#: Elements that declare themselves the article.
MAIN_ELEMENTS, MAIN_ROLES = frozenset(("article", "main")), frozenset(("main", "article"))
#: Elements that start and end a block.
BLOCKS = frozenset(
    "address article blockquote body caption center dd details div dl dt fieldset figcaption figure h1 h2 h3 h4 h5 h6 header hr html li main ol p "
    "pre section summary table tbody td tfoot th thead tr ul".split()
)
VOID = frozenset("area base br col embed hr img input link meta param source track wbr".split())
RAW = frozenset(("script", "style", "textarea", "title", "xmp", "iframe", "noembed", "noframes"))
#: An open element that ends where one of these starts.
ENDS_AT = {"p": BLOCKS, "li": frozenset(("li",)), "dt": frozenset(("dt", "dd")), "dd": frozenset(("dt", "dd")), "tr": frozenset(("tr",)), "td": frozenset(("td", "th", "tr")), "th": frozenset(("td", "th", "tr")), "option": frozenset(("option",))}
#: Where an implied end stops looking outwards.
SCOPE = frozenset("table ul ol dl div section article main aside nav header footer form body html blockquote button".split())

_TOKEN = re.compile(
    r"<!--.*?(?:-->|\Z)|<!\[CDATA\[(?P<cdata>.*?)(?:\]\]>|\Z)|<[!?][^>]*(?:>|\Z)"
    r"|<(?P<end>/?)(?P<tag>[a-zA-Z][^\s/>]*)(?P<rest>(?:[^>\"']|\"[^\"]*\"|'[^']*'|[\"'])*?)(?:>|\Z)",
    re.S,
)
_MARKS = re.compile(r"""(?:^|[\s"'/])(class|id|role)\s*=\s*(?:"([^"]*)"|'([^']*)'|([^\s>]+))""", re.I)
_SPACE = re.compile(r"\s+")


def _declares(tag: str, rest: str) -> int:
    """-2: no line of the page, -1: not the article, 1: the article, 0: nothing."""
    kind = -2 if tag in HIDDEN else -1 if tag in ASIDE else 1 if tag in MAIN_ELEMENTS else 0
    if kind >= 0 and rest and "=" in rest:
        for name, *values in _MARKS.findall(rest):
            value = next((v for v in values if v), "").lower()
            if name.lower() == "role" and value in MAIN_ROLES:
                kind = 1
            elif kind == 0 and tag not in ("body", "html") and BOILERPLATE_WORDS & set(re.split(r"[^a-z0-9]+", re.sub(r"(?<=[a-z])(?=[A-Z])", "-", value))):
                return -1
    return kind


def page_lines(page: str) -> list[tuple[int, str]]:
    """(kind, text) of each line of text, in page order; kinds as _declares has them, of the elements around the line."""
    lines: list[tuple[int, str]] = []
    parts: list[str] = []
    stack: list[tuple[str, int]] = []  # (tag, declares)
    hidden = aside = mains = 0
    at, n = 0, len(page)

    def flush() -> None:
        if parts:
            text = _SPACE.sub(" ", entities.unescape("".join(parts))).strip()
            if text:
                lines.append((-1 if aside else 1 if mains else 0, text))
            parts.clear()

    def close(depth: int) -> None:
        nonlocal hidden, aside, mains
        while len(stack) > depth:
            tag, kind = stack.pop()
            if (tag in BLOCKS or kind) and not hidden:
                flush()
            hidden -= kind == -2
            aside -= kind == -1
            mains -= kind == 1

    while at < n:
        m = _TOKEN.search(page, at)
        stop = m.start() if m else n
        if stop > at and not hidden:
            parts.append(page[at:stop])
        if not m:
            break
        at = m.end()
        tag = m["tag"]
        if tag is None:
            if m["cdata"] is not None and not hidden:
                parts.append(m["cdata"].replace("&", "&amp;"))
            continue
        tag = tag.lower()
        if m["end"]:
            for depth in range(len(stack) - 1, -1, -1):
                if stack[depth][0] == tag:
                    close(depth)
                    break
            continue
        if tag == "br" and not hidden:
            parts.append(" ")
        for depth in range(len(stack) - 1, -1, -1):
            if tag in ENDS_AT.get(stack[depth][0], ()):
                close(depth)
                break
            if stack[depth][0] in SCOPE:
                break
        kind = _declares(tag, m["rest"])
        if tag == "header":  # of the page, not of the article
            kind = 0 if mains else -1
        if (tag in BLOCKS or kind) and not hidden:
            flush()
        if tag in VOID:
            continue
        if tag in RAW:
            end = re.compile(rf"</{tag}\s*>|\Z", re.I).search(page, at)
            if kind >= 0 and not hidden:
                parts.append(page[at : end.start()])
            at = end.end()
            continue
        if m["rest"].endswith("/") and tag in ("svg", "path"):
            continue
        stack.append((tag, kind))
        hidden += kind == -2
        aside += kind == -1
        mains += kind == 1
    if not hidden:
        flush()
    return lines


#: Bits that one alignment may keep; longer pages are aligned by halves.
ALIGN_BITS = 1 << 28


def _steps(a: list, where: dict, full: int) -> Iterator[int]:
    """After each line of a, the bits of b: zero where the longest common subsequence grows."""
    v = full
    for x in a:
        u = v & where.get(x, 0)
        v = ((v + u) | (v - u)) & full
        yield v


def _places(b: list) -> dict:
    where: dict = {}
    for j, x in enumerate(b):
        where[x] = where.get(x, 0) | 1 << j
    return where


def shared_lines(a: list, b: list) -> set[int]:
    """Places in a on one longest common subsequence of a and b. Bit-parallel; equal ends first; in halves if it is long."""
    low, n = 0, min(len(a), len(b))
    while low < n and a[low] == b[low]:
        low += 1
    high = 0
    while high < n - low and a[-1 - high] == b[-1 - high]:
        high += 1
    out = set(range(low)) | set(range(len(a) - high, len(a)))
    common = set(a[low : len(a) - high]) & set(b[low : len(b) - high])
    if not common:
        return out
    ia = [i for i in range(low, len(a) - high) if a[i] in common]
    x, y = [a[i] for i in ia], [z for z in b[low : len(b) - high] if z in common]
    full = (1 << len(y)) - 1
    if len(x) * len(y) > ALIGN_BITS and len(x) > 1:
        half = len(x) // 2
        for first in _steps(x[:half], _places(y), full):
            pass
        for last in _steps(x[:half - 1 : -1], _places(y[::-1]), full):
            pass
        ahead = [0]
        for j in range(len(y)):
            ahead.append(ahead[-1] + (not first >> j & 1))
        behind, best, cut = 0, -1, 0
        for j in range(len(y), -1, -1):
            if ahead[j] + behind > best:
                best, cut = ahead[j] + behind, j
            behind += not last >> (len(y) - j) & 1
        return out | {ia[i] for i in shared_lines(x[:half], y[:cut])} | {ia[half + i] for i in shared_lines(x[half:], y[cut:])}
    where = _places(y)
    rows = list(_steps(x, where, full))
    j = len(y)
    for k in range(len(x) - 1, -1, -1):
        if not j:
            break
        mask = (1 << j) - 1
        now = ~rows[k] & mask
        before = (~rows[k - 1] & mask) if k else 0
        if now.bit_count() > before.bit_count():
            # line k is needed; it matches at the highest place where the count is reached
            top = now.bit_length() - 1
            hit = where[x[k]] & mask & ~((1 << top) - 1)
            out.add(ia[k])
            j = (hit & -hit).bit_length() - 1 if hit else top
    return out


# ---------------------------------------------------------------- Spark

#: Pages with template lines, and bytes of their marks, that are broadcast; more are joined.
BROADCAST_PAGES, BROADCAST_BYTES = 500_000, 32 << 20


def _line_hashes(lines: list[tuple[int, str]]) -> np.ndarray:
    """Lines are equal if their texts are, and either both or none stand in an article."""
    return np.array([xxhash.xxh3_64_intdigest(("+" if k > 0 else "-") + t) for k, t in lines], dtype=np.uint64).view(np.int64)


def _signature(hashes: np.ndarray) -> str | None:
    return xxhash.xxh3_128_hexdigest(hashes.tobytes()) if len(hashes) else None


def _place(url: str) -> list[Column]:
    link = F.coalesce(F.col(url).cast("string"), F.lit(""))
    host = F.lower(F.regexp_extract(link, r"^[A-Za-z][A-Za-z0-9+.-]*://([^/?#]*)", 1))
    return [host.alias("host"), F.regexp_extract(link, r"^(?:[A-Za-z][A-Za-z0-9+.-]*://[^/?#]*)?([^?#]*)", 1).alias("path")]


def line_names(pages: DataFrame, *, id_col: str, url_col: str, html_col: str) -> DataFrame:
    """(uid, id, host, path, sig, hashes): the hashes of the lines of every page that has some."""

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in batches:
            hashes = [_line_hashes(page_lines(x.as_py() or "")) for x in batch.column(3)]
            arrays = [*batch.columns[:3], pa.array(map(_signature, hashes), pa.string()), pa.array(hashes, pa.list_(pa.int64()))]
            yield pa.RecordBatch.from_arrays(arrays, names=["id", "host", "path", "sig", "hashes"])

    kind = pages.schema[id_col].dataType.simpleString()
    rows = pages.select(F.col(id_col), *_place(url_col), F.col(html_col)).mapInArrow(run, f"id {kind}, host string, path string, sig string, hashes array<long>")
    return rows.where("sig is not null").select(F.monotonically_increasing_id().alias("uid"), "*")


def _leading_segments(a: Column, b: Column) -> Column:
    """Leading path segments that a and b have in common."""
    same = F.zip_with(F.split(a, "/"), F.split(b, "/"), lambda x, y: x.eqNullSafe(y))
    grow = lambda n, e: F.when((n >= 0) & e, n + 1).when(n >= 0, -n - 1).otherwise(n)
    return F.aggregate(same, F.lit(0), grow, lambda n: F.when(n < 0, -n - 1).otherwise(n))


def partners(named: DataFrame) -> DataFrame:
    """(host, sig, uid, partner): for each distinct page of a host, the uid of the page it is compared with."""
    first = named.groupBy("host", "sig").agg(F.min(F.struct("path", "id", "uid")).alias("at"))
    order = ranked(first.select("host", "sig", "at.path", "at.id", "at.uid"), ["host", "path", "id", "uid"], "rank")
    near = []
    for step in (1, -1):
        side = order.select((F.col("rank") + step).alias("rank"), F.col("host").alias("host_n"), F.col("path").alias("path_n"), F.col("uid").alias("uid_n"))
        near.append(order.join(side, "rank").where("host = host_n").withColumn("like", _leading_segments(F.col("path"), F.col("path_n"))).withColumn("before", F.lit(step)))
    best = near[0].unionByName(near[1]).groupBy("uid").agg(F.max(F.struct("like", "before", "uid_n")).alias("best"), F.first("host").alias("host"), F.first("sig").alias("sig"))
    return best.select("host", "sig", "uid", F.col("best.uid_n").alias("partner"))


def template_lines(named: DataFrame) -> DataFrame:
    """(host, sig, shared): a bit per line, set if it is on the common subsequence with the page's partner; pages that share none are left out."""
    pairs = materialize(partners(named), "partners")
    own = named.select("uid", "hashes")
    other = named.select(F.col("uid").alias("partner"), F.col("hashes").alias("others"))

    def align(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in batches:
            marks = []
            for a, b in zip(batch.column(2).to_pylist(), batch.column(3).to_pylist(), strict=True):
                hit = shared_lines(a, b)
                bits = np.zeros(len(a), dtype=bool)
                bits[list(hit)] = True
                marks.append(np.packbits(bits).tobytes() if hit else None)
            out = pa.RecordBatch.from_arrays([batch.column(0), batch.column(1), pa.array(marks, pa.binary())], names=["host", "sig", "shared"])
            yield out.filter(out.column(2).is_valid())

    return pairs.join(own, "uid").join(other, "partner").select("host", "sig", "hashes", "others").mapInArrow(align, "host string, sig string, shared binary")


def extract_pages(pages: DataFrame, *, id_col: str = "page_id", url_col: str = "url", html_col: str = "html") -> DataFrame:
    """id, url, text, n_chars of every page; n_lines of it, n_shared with its partner, n_template: those deleted by differencing.

    A page with copies on its host is aligned once; its copies take the same lines. Pages are read twice, once for the hashes;
    the marks of template lines are broadcast if they are counted to be few, else compressed lines are shuffled to them.
    """
    named = materialize(line_names(pages, id_col=id_col, url_col=url_col, html_col=html_col), "named")
    shared = materialize(template_lines(named), "shared")
    rows, size = shared.agg(F.count("*"), F.coalesce(F.sum(F.octet_length("shared")), F.lit(0))).first()
    kind, link = (pages.schema[c].dataType.simpleString() for c in (id_col, url_col))

    def parse(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        pack = zstandard.ZstdCompressor(level=3).compress
        for batch in batches:
            sigs, kinds, texts = [], [], []
            for page in batch.column(3):
                lines = page_lines(page.as_py() or "")
                sigs.append(_signature(_line_hashes(lines)))
                kinds.append(bytes(k + 1 for k, _ in lines))
                # No line holds a line feed, as white space is one blank.
                texts.append(pack("\n".join(t if k >= 0 else "" for k, t in lines).encode("utf-8", "surrogatepass")))
            arrays = [*batch.columns[:3], pa.array(sigs, pa.string()), pa.array(kinds, pa.binary()), pa.array(texts, pa.binary())]
            yield pa.RecordBatch.from_arrays(arrays, names=["id", "url", "host", "sig", "kinds", "texts"])

    def keep(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        unpack = zstandard.ZstdDecompressor().decompress
        for batch in batches:
            out = []
            for kinds, texts, mark in zip(*(c.to_pylist() for c in batch.columns[2:]), strict=True):
                lines = unpack(texts).decode("utf-8", "surrogatepass").split("\n") if kinds else []
                hit = np.unpackbits(np.frombuffer(mark, dtype=np.uint8), count=len(lines)).tolist() if mark else [0] * len(lines)
                declared = 2 in kinds
                kept = [t for t, k, h in zip(lines, kinds, hit, strict=True) if k == 2 or (k == 1 and not declared and not h)]
                text = "\n".join(kept)
                out.append((text, len(text), len(lines), sum(hit), sum(h and k < 2 for h, k in zip(hit, kinds, strict=True))))
            columns = zip(*out, strict=True) if out else [()] * 5
            arrays = [pa.array(c, t) for c, t in zip(columns, (pa.string(), *[pa.int64()] * 4), strict=True)]
            yield pa.RecordBatch.from_arrays([*batch.columns[:2], *arrays], names=[id_col, url_col, "text", "n_chars", "n_lines", "n_shared", "n_template"])

    parsed = pages.select(F.col(id_col), F.col(url_col), _place(url_col)[0], F.col(html_col)).mapInArrow(
        parse, f"id {kind}, url {link}, host string, sig string, kinds binary, texts binary"
    )
    few = rows <= BROADCAST_PAGES and size <= BROADCAST_BYTES
    joined = parsed.join(F.broadcast(shared) if few else shared, ["host", "sig"], "left").select("id", "url", "kinds", "texts", "shared")
    return joined.mapInArrow(keep, f"`{id_col}` {kind}, `{url_col}` {link}, text string, n_chars long, n_lines long, n_shared long, n_template long")
