"""Main-text extraction from web pages with nearest-URL page differencing.

A page is parsed into lines of text, one for each block. Every page is paired with the nearest pages by URL path on its
host, the lines of both are aligned by longest common subsequence, and shared lines, the template, are deleted. Lines
inside a marked article (``article``, ``main``) are protected, since articles repeat passages of each other. Of
the lines that differencing leaves, those in menus, forms, adverts, notices, comments and the like go by tag and by the
words of class, id and role, and if the page marks its article, those outside of it. Pages that share most of their
text are copies of one article, not of one template; the next nearest page is taken instead.
"""

from __future__ import annotations

import bisect
import hashlib
import html as entities
import re
from collections.abc import Iterator
from dataclasses import dataclass
from urllib.parse import urlsplit

import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F
from pyspark.sql.window import Window

from .common import durable, sized_broadcast

TAG = re.compile(r"""<!--.*?(?:-->|\Z)|<(/?)([a-zA-Z][^\s/>]*)((?:"[^"]*"|'[^']*'|[^'">])*+)>|<(/?)([a-zA-Z][^\s/>]*)([^>]*)>|<[!?][^>]*>""", re.S)
ATTR = re.compile(r"""([a-zA-Z-]+)\s*=\s*("[^"]*"|'[^']*'|[^\s"'>]+)""")

#: Elements without text of their own, dropped elements, elements that end a block, void elements.
RAW = frozenset("script style title textarea noscript template iframe object svg math head xmp".split())
DROPPED = frozenset("nav footer aside form button select dialog menu".split())
BLOCK = frozenset("address article aside blockquote body caption dd details div dl dt fieldset figcaption figure footer form h1 h2 h3 h4 h5 h6 header hr html legend li main nav ol p pre section summary table tbody td tfoot th thead tr ul".split())
VOID = frozenset("area base br col embed hr img input link meta param source track wbr".split())
NOISE = frozenset(
    "ad ads advert adverts advertisement advertising sponsor sponsored promo promotion banner cookie cookies consent gdpr notice notices alert popup modal overlay "
    "sidebar menu navbar navigation nav breadcrumb breadcrumbs footer masthead topbar toolbar share sharing social related recommended comment comments disqus "
    "reply replies newsletter subscribe subscription signup login search pagination pager widget toc skip complementary contentinfo hidden".split()
)
HEAD_WORDS = frozenset("header banner masthead".split())
RIGHTS = ("©", "(c) ", "Copyright")


def _noisy(tag: str, attrs: str, inside: bool) -> bool:
    if tag in DROPPED or tag == "header" and not inside:
        return True
    if tag in ("body", "html", "article", "main") or not attrs:
        return False
    low = attrs.lower()
    if re.search(r"(?:^|\s)hidden(?:\s|=|/|$)", low) or "display:none" in low.replace(" ", ""):
        return True
    for name, value in ATTR.findall(low):
        if name in ("class", "id", "role"):
            words = set(re.split(r"[^a-z0-9]+", value))
            if words & NOISE or not inside and words & HEAD_WORDS:
                return True
    return False


@dataclass(frozen=True)
class Line:
    """``inside``: in a marked article; ``noisy``: in an element that is no main text; ``linked``: all of it links."""

    text: str
    inside: bool
    noisy: bool
    linked: bool

    @property
    def protected(self) -> bool:
        return self.inside and not self.noisy


def parse(page: str) -> list[Line]:
    """All lines of the page but those of scripts, styles and the like."""
    lines: list[Line] = []
    buf: list[str] = []
    inside, links, linked, at = 0, 0, True, 0
    skip_tag, skip_depth = "", 0

    def close() -> None:
        nonlocal linked
        if buf:
            if text := " ".join(entities.unescape("".join(buf)).split()):
                lines.append(Line(text, inside > 0, skip_depth > 0, linked))
            buf.clear()
        linked = True

    while True:
        m = TAG.search(page, at)
        if piece := page[at : m.start() if m else len(page)]:
            buf.append(piece)
            linked = linked and (links > 0 or piece.isspace())
        if not m:
            break
        at = m.end()
        slash, tag, attrs = (m[1], m[2], m[3]) if m[2] else (m[4], m[5], m[6])
        if not tag:
            continue
        tag = tag.lower()
        if not slash and tag in RAW and not (attrs or "").endswith("/"):
            end = re.compile(rf"</{tag}\s*>", re.I).search(page, at)
            if end is None and tag == "head":
                end = re.compile(r"<body", re.I).search(page, at)
                at = end.start() if end else at
            elif tag != "head" or end:
                at = end.end() if end else len(page)
            continue
        if tag == "a":
            links = max(0, links + (-1 if slash else 1))
        elif tag == "br":
            buf.append(" ")
            continue
        if tag in BLOCK or tag in DROPPED:
            close()
            links = 0
        if skip_depth:
            if tag in ("article", "main") and not slash and skip_tag not in ("article", "aside", "section"):
                close()
                skip_depth = 0
            else:
                if tag == skip_tag:
                    if slash and skip_depth == 1:
                        close()
                    skip_depth += -1 if slash else 1
                continue
        if not slash and tag not in VOID and _noisy(tag, attrs or "", inside > 0):
            close()
            skip_tag, skip_depth = tag, 1
            continue
        if tag in ("article", "main"):
            inside = max(0, inside + (-1 if slash else 1))
    close()
    return lines


def main_lines(lines: list[Line], shared: set[int]) -> tuple[list[str], int]:
    """The main text, and how many of the lines that differencing left went by tag, class word or mark."""
    left = [x for i, x in enumerate(lines) if i not in shared or x.protected]
    marked = any(x.protected for x in lines)
    kept = [x.text for x in left if not x.noisy and (x.inside if marked else not (x.linked or x.text.startswith(RIGHTS)))]
    return kept, len(left) - len(kept)


def longest_common(a: list[int], b: list[int]) -> list[int]:
    """Places in ``a`` of one longest common subsequence with ``b``, by increasing runs over matching places."""
    where: dict[int, list[int]] = {}
    for j, x in enumerate(b):
        where.setdefault(x, []).append(j)
    tops: list[int] = []
    nodes: list[tuple[int, object]] = []
    for i, x in enumerate(a):
        for j in reversed(where.get(x, ())):
            k = bisect.bisect_left(tops, j)
            node = (i, nodes[k - 1] if k else None)
            if k == len(tops):
                tops.append(j)
                nodes.append(node)
            else:
                tops[k], nodes[k] = j, node
    out, node = [], nodes[-1] if nodes else None
    while node is not None:
        out.append(node[0])
        node = node[1]
    return out[::-1]


def shared_lines(a: list[int], b: list[int], weights: list[int], copy_share: float) -> list[int]:
    """Lines of ``a`` to delete for a partner ``b``; none if they make up ``copy_share`` of the text, as in a copy."""
    found = longest_common(a, b)
    return [] if not found or sum(weights[i] for i in found) >= copy_share * max(1, sum(weights)) else found


def _line_key(text: str) -> int:
    return int.from_bytes(hashlib.blake2b(text.encode("utf-8", "replace"), digest_size=8).digest(), "little", signed=True)


def _address(url: str | None) -> tuple[str, str]:
    try:
        u = urlsplit(url or "")
        return (u.hostname or "").removeprefix("www."), u.path or "/"
    except ValueError:
        return "", url or ""


def _near(a: str, b: str) -> int:
    x, y = a.split("/"), b.split("/")
    n = next((i for i, (p, q) in enumerate(zip(x, y, strict=False)) if p != q), min(len(x), len(y)))
    return 2 * n - len(x) - len(y)


PAGE_LINES = "page_id long, hk long, host string, path string, lk long, keys array<bigint>, weights array<int>, safe array<boolean>"
TYPES = {"long": pa.int64(), "string": pa.string(), "array<bigint>": pa.list_(pa.int64()), "array<int>": pa.list_(pa.int32()), "array<boolean>": pa.list_(pa.bool_())}


def _batch(rows: list[tuple], schema: str) -> pa.RecordBatch:
    fields = [x.split() for x in schema.split(", ")]
    cols = list(zip(*rows, strict=True)) or [()] * len(fields)
    return pa.RecordBatch.from_arrays([pa.array(list(c), TYPES[t]) for c, (_, t) in zip(cols, fields, strict=True)], [n for n, _ in fields])


def page_lines(pages: DataFrame) -> DataFrame:
    """Hashes and lengths of the lines of each page, ``lk`` standing for all of them, and which lines are protected."""

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for b in batches:
            rows = []
            for page_id, hk, url, text in zip(*[c.to_pylist() for c in b.columns], strict=True):
                lines = parse(text or "")
                if any(not x.protected for x in lines):
                    keys = [_line_key(x.text) for x in lines]
                    rows.append((page_id, hk, *_address(url), _line_key(repr((keys, [x.protected for x in lines]))), keys, [len(x.text) for x in lines], [x.protected for x in lines]))
            yield _batch(rows, PAGE_LINES)

    return pages.select("page_id", "hk", "url", "html").mapInArrow(run, PAGE_LINES)


def template_lines(pages: DataFrame, copy_share: float = 0.8, beside: int = 3) -> DataFrame:
    """``(page_id, hk, cut)``: numbers of the lines that each page shares with the nearest page that is no copy of it.

    Pages of a host with the same lines are one. They are put in order of host, path and id by ranges, so a host with
    very many pages spreads over tasks; the outermost pages of each range are also given to its neighbours, and every
    page looks at up to ``beside`` pages on either side, the nearest path first.
    """
    own = durable(page_lines(pages))
    order = ["host", "path", "page_id", "lk"]
    first = F.min(F.struct("path", "page_id", "keys", "weights", "safe"))
    alone = own.groupBy("host", "lk").agg(first.alias("o")).select("host", "lk", "o.*")
    ranged = durable(alone.repartitionByRange(*order).withColumn("part", F.spark_partition_id()))
    used = ranged.select("part").distinct().withColumn("rank", F.row_number().over(Window.orderBy("part")))  # one row per partition
    ranged = ranged.join(F.broadcast(used), "part").drop("part").withColumn("ghost", F.lit(False))

    def outermost(way, step: int) -> DataFrame:
        k = F.row_number().over(Window.partitionBy("rank").orderBy(*[way(c) for c in order]))
        return ranged.withColumn("k", k).where(F.col("k") <= beside).drop("k").withColumns({"rank": F.col("rank") + step, "ghost": F.lit(True)})

    dealt = ranged.unionByName(outermost(F.asc, -1)).unionByName(outermost(F.desc, 1))
    dealt = dealt.repartition("rank").sortWithinPartitions("rank", *order)
    names = "host string, lk long, cut array<int>"

    def differ(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        def cut(r: dict, near: list[tuple[int, dict]]) -> list[int]:
            others = [(d, x) for d, x in near if (x["rank"], x["host"]) == (r["rank"], r["host"])]
            for _, other in sorted(others, key=lambda o: (-_near(r["path"], o[1]["path"]), o[0])):
                found = shared_lines(r["keys"], other["keys"], r["weights"], copy_share)
                if found := [i for i in found if not r["safe"][i]]:
                    return found
            return []

        window: list[dict] = []  # up to `beside` rows before, one to decide, up to `beside` rows after
        at = 0

        def decided(last: bool) -> Iterator[tuple]:
            nonlocal at
            while at < len(window) and (last or len(window) - at > beside):
                r = window[at]
                if not r["ghost"]:
                    near = [(abs(at - j), window[j]) for j in range(max(0, at - beside), min(len(window), at + beside + 1)) if j != at]
                    if found := cut(r, near):
                        yield r["host"], r["lk"], found
                at += 1
                if at > beside:
                    window.pop(0)
                    at -= 1

        for b in batches:
            rows = []
            for r in b.to_pylist():
                window.append(r)
                rows += decided(False)
            yield _batch(rows, names)
        yield _batch(list(decided(True)), names)

    cuts = dealt.mapInArrow(differ, names)
    return durable(own.select("page_id", "hk", "host", "lk").join(cuts, ["host", "lk"]).select("page_id", "hk", "cut"))


def extract_text(pages: DataFrame, id_col: str = "page_id", url_col: str = "url", html_col: str = "html", copy_share: float = 0.8, beside: int = 3, broadcast_bytes: int = 64 << 20) -> DataFrame:
    """``page_id, url, text, n_chars, n_lines, n_shared, n_marks`` for every row: kept lines joined by two line feeds, empty
    if there is none; all lines, those which differencing deleted, and those which went by tag, class or mark.

    A null page counts as empty; broken and cut markup is read as far as it goes; a null url puts the page on the host
    without a name; repeated rows give equal results; an empty table gives an empty result. The table of shared lines
    is broadcast within ``broadcast_bytes``; beyond it pages are shuffled by their id.
    """
    own = pages.select(F.col(id_col).cast("long").alias("page_id"), F.col(url_col).cast("string").alias("url"), F.col(html_col).cast("string").alias("html"))
    own = own.withColumn("hk", F.xxhash64("html", "url"))
    cuts = template_lines(own, copy_share, beside).select(F.col("page_id").alias("i"), F.col("hk").alias("k"), "cut").dropDuplicates(["i", "k"])
    cuts = sized_broadcast(cuts, broadcast_bytes)
    joined = own.join(cuts, F.col("page_id").eqNullSafe(F.col("i")) & (F.col("hk") == F.col("k")), "left")
    schema = "page_id long, url string, text string, n_chars long, n_lines long, n_shared long, n_marks long"

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for b in batches:
            rows = []
            for text, shared in zip(b.column(2), b.column(3), strict=True):
                lines, drop = parse(text.as_py() or ""), set(shared.as_py() or ())
                kept, marks = main_lines(lines, drop)
                whole = "\n\n".join(kept)
                rows.append((whole, len(whole), len(lines), len(drop), marks))
            made = _batch(rows, schema.split(", ", 2)[2])
            yield pa.RecordBatch.from_arrays([b.column(0), b.column(1), *made.columns], [x.split()[0] for x in schema.split(", ")])

    return joined.select("page_id", "url", "html", "cut").mapInArrow(run, schema)
