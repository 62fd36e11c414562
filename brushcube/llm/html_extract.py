"""Main text of web pages: nearest-URL page differencing, checked by the marks of articles.

A page is cut into blocks by a tolerant parser that leaves out what can't be main text (scripts, styles, comments, menus,
headers, footers, sidebars, forms, and elements whose class, id or role says advert, notice, reader comments and the like). Every page, whether it
marks its article or not, is then compared with another of its host: pages of a host are sorted by URL path, each is paired with the neighbour that
shares the longest path prefix, their lines are aligned by longest common subsequence, and lines that both have are template text; the others are
the page's own. A page whose neighbours are all copies of it loses nothing to them: the next different page is taken, and without one all its lines are own.

Where the page marks its article (``article``, ``main`` or role=main), the marks check that result line by line: shared lines inside are article
text that two pages have, and come back (``restored``); own lines outside go (``left_out``). Else the own lines are the text.
Differencing alone can't give the contract's text: it keeps what differs between pages of a host outside their articles, and
deletes article lines that two pages share. See the README for figures.

Lines are compared by digests of 128 bits, and a page's outcome finds its text again by a digest of the whole row; so texts are exchanged once.
For that ``pages`` is read twice: it must hold the same rows both times.

Hosts of any size: pages that need a partner are ordered by host and URL and cut into ranges of at most GROUP pages, so that no host is ever
in one task. In front of and behind its pages, a range has a guest where the host goes on: a copy of the nearest page outside that differs
from the range's first (last) page. So each page meets the partner it would meet if its host were whole, whatever GROUP is.

Defined results: a null or empty html has empty text; a null url belongs to an empty host; repeated pages are copies, as above; references
cut off at the end are decoded as browsers do; every white-space run becomes one space, blocks are joined in order by one space.
"""

from __future__ import annotations

import hashlib
import html as entities
import re
from collections.abc import Iterator
from dataclasses import dataclass

import pandas as pd
from pyspark.sql import Column, DataFrame, SparkSession
from pyspark.sql import Window as W
from pyspark.sql import functions as F

from .common import hand_over, release, table
from .url_filter import host_of, path_of

GROUP = 400
#: Elements that never hold main text, elements without content, and elements that break lines.
DROPPED = frozenset("head script style noscript template iframe object svg math canvas video audio nav header footer aside form button select textarea dialog menu".split())
VOID = frozenset("area base br col embed hr img input link meta param source track wbr".split())
BLOCKS = frozenset("address article blockquote body caption center dd details div dl dt fieldset figcaption figure h1 h2 h3 h4 h5 h6 hr html legend li main ol p pre section summary table tbody td tfoot th thead tr ul".split()) | DROPPED
RAW = frozenset("script style textarea noscript iframe template svg math".split())
#: Words in class, id or role that mark what is not the article.
MARKED = re.compile(
    r"(?:^|[\s_-])(?:ads?|advert\w*|adsense|banner|sponsor\w*|promo\w*|side-?bar|menu|nav\w*|breadcrumbs?|cookies?|consent|gdpr|notices?|newsletter|subscri\w+|popup|modal|"
    r"share|sharing|social|related|recommend\w*|comments?|repl(?:y|ies)|disqus|footer|header|masthead|toolbar|login|signup|search|complementary|contentinfo|navigation)(?:$|[\s_-])", re.I)
#: Opening one of these ends an open element of the listed names.
ENDS = {"li": {"li"}, "dt": {"dt", "dd"}, "dd": {"dt", "dd"}, "tr": {"tr", "td", "th"}, "td": {"td", "th"}, "th": {"td", "th"}, "option": {"option"}}
#: Quoted values go to their closing quote. Possessive, so linear: tags tried in vain that run over one place differ in their state (outside, in ", in '), so there are three at most.
_TOKEN = re.compile(
    r"<!--.*?(?:--!?>|\Z)|<!\[CDATA\[.*?(?:\]\]>|\Z)|<[!?][^>]*(?:>|\Z)|<(/?)([a-zA-Z][^\s/<>]*)((?:[^\"'<>]++|\"[^\"]*+\"|'[^']*+')*+|[^<>]*)>", re.S)
_ATTRIBUTE = re.compile(r"(class|id|role|hidden|style|aria-hidden)\s*(?:=\s*(?:\"([^\"]*)\"|'([^']*)'|([^\s\"'>]+)))?", re.I)


@dataclass
class Open:
    name: str
    dropped: bool
    article: bool


def _kind(name: str, attributes: str) -> tuple[bool, bool]:
    """(dropped, article) of an element by its tag."""
    dropped, article = name in DROPPED, name in ("article", "main")
    for key, a, b, c in _ATTRIBUTE.findall(attributes) if attributes.strip() else ():
        key, value = key.lower(), (a or b or c)
        if key == "hidden" or (key == "aria-hidden" and value == "true") or (key == "style" and re.search(r"display\s*:\s*none", value, re.I)):
            dropped = True
        elif key == "role" and value.lower() in ("main", "article"):
            article = True
        elif key in ("class", "id", "role") and name not in ("html", "body") and MARKED.search(value):
            dropped = True
    return dropped, article


def page_lines(html: str | None) -> tuple[list[str], bool]:
    """The page's lines of possible main text, and whether they are a marked article's."""
    every, inside, saw = page_blocks(html)
    return ([t for t, i in zip(every, inside, strict=True) if i], True) if saw else (every, False)


def page_blocks(html: str | None) -> tuple[list[str], list[bool], bool]:
    """All lines of possible main text, for each whether it is in a marked article, and whether the page marks one."""
    every: list[str] = []
    inside: list[bool] = []
    stack: list[Open] = []
    parts: list[str] = []
    in_article, saw, dropped, text_at = 0, False, 0, 0

    def line() -> None:
        if parts:
            if t := " ".join("".join(parts).split()):
                every.append(t)
                inside.append(in_article > 0)
            parts.clear()

    def pop(to: int) -> None:
        nonlocal in_article, dropped
        while len(stack) > to:
            o = stack.pop()
            if o.name in BLOCKS or o.dropped or o.article:
                line()
            dropped -= o.dropped
            in_article -= o.article

    html, at = html or "", 0
    while True:
        m = _TOKEN.search(html, at)
        end = m.start() if m else len(html)
        if end > text_at and not dropped:
            parts.append(entities.unescape(html[text_at:end]))
        if not m:
            break
        at = text_at = m.end()
        if not m[2]:
            continue
        name = m[2].lower()
        if m[1]:
            for i in range(len(stack) - 1, -1, -1):
                if stack[i].name == name:
                    pop(i)
                    break
            else:
                if name in BLOCKS and not dropped:
                    line()
            continue
        if name == "br":
            if not dropped:
                parts.append(" ")
            continue
        if name in VOID:
            if name == "hr" and not dropped:
                line()
            continue
        if name in BLOCKS or name in ENDS:
            for i in range(len(stack) - 1, -1, -1):  # an open paragraph or list item ends here
                if stack[i].name in ENDS.get(name, ()) or (stack[i].name == "p" and name in BLOCKS):
                    pop(i)
                    break
                if stack[i].name in BLOCKS:
                    break
            if not dropped:
                line()
        if name in RAW:
            close = re.compile(rf"</{re.escape(name)}(?=[\s/>])[^>]*>|</{re.escape(name)}\Z", re.I).search(html, at)
            at = text_at = close.end() if close else len(html)
            continue
        if (m[3] or "").endswith("/") and name not in BLOCKS:
            continue
        drop, article = _kind(name, m[3] or "")
        article = article and not drop and not dropped
        stack.append(Open(name, drop, article))
        dropped += drop
        in_article += article
        saw = saw or article
    line()
    return every, inside, saw


def common_lines(a: list, b: list) -> set[int]:
    """Places in ``a`` of a longest common subsequence with ``b``: bit-parallel rows, then one way back."""
    head = 0
    while head < min(len(a), len(b)) and a[head] == b[head]:
        head += 1
    tail = 0
    while tail < min(len(a), len(b)) - head and a[-1 - tail] == b[-1 - tail]:
        tail += 1
    kept = set(range(head)) | set(range(len(a) - tail, len(a)))
    x, y = a[head : len(a) - tail], b[head : len(b) - tail]
    masks: dict = {}
    for j, t in enumerate(y):
        masks[t] = masks.get(t, 0) | 1 << j
    full = (1 << len(y)) - 1
    v, rows = full, []
    for t in x:
        u = v & masks.get(t, 0)
        v = ((v + u) | (v - u)) & full
        rows.append(v)
    i, j = len(x), len(y)
    while i and j:
        if rows[i - 1] >> (j - 1) & 1:
            j -= 1
        elif i > 1 and not rows[i - 2] >> (j - 1) & 1:
            i -= 1
        else:
            kept.add(head + i - 1)
            i, j = i - 1, j - 1
    return kept


def difference(pages: list[tuple[str, list]]) -> list[list[bool]]:
    """Per (path, lines), in path order: for each line, whether its nearest different page doesn't share it."""

    def shared(p: str, q: str) -> int:
        n = 0
        for c, d in zip(p, q):
            if c != d:
                break
            n += 1
        return n

    def nearest(places: range, step: int) -> list[int | None]:
        """For each page, the first one in front (behind, by step) with other lines."""
        found: list[int | None] = [None] * len(pages)
        for k in places:
            found[k] = k + step if pages[k][1] != pages[k + step][1] else found[k + step]
        return found

    left, right = nearest(range(1, len(pages)), -1), nearest(range(len(pages) - 2, -1, -1), 1)
    out = []
    for k, (path, lines) in enumerate(pages):
        lo, hi = left[k], right[k]
        # Prefixes only get shorter away from a page, so of the two the nearer one shares more (or is in front).
        if lo is None or (hi is not None and shared(path, pages[lo][0]) < shared(path, pages[hi][0])):
            lo = hi
        gone = common_lines(lines, pages[lo][1]) if lo is not None else set()
        out.append([i not in gone for i in range(len(lines))])
    return out


def _guests(order: DataFrame) -> DataFrame:
    """deal, place: the rows that stand as guests in a range. ``order``: host, place, deal, sig (which equal lines have in common)."""
    ends = order.groupBy("host", "deal").agg(F.min("place").alias("first"), F.max("place").alias("last"), F.min_by("sig", "place").alias("first_sig"), F.max_by("sig", "place").alias("last_sig"))
    inner = order.join(ends, ["host", "deal"]).groupBy("host", "deal", "first", "last", "first_sig", "last_sig").agg(
        F.max(F.when(F.col("sig") != F.col("last_sig"), F.col("place"))).alias("last_other"), F.min(F.when(F.col("sig") != F.col("first_sig"), F.col("place"))).alias("first_other"))

    def outside(turn: W, sig: str, met: str, met_sig: str, other: str) -> Column:
        """The nearest row with another sig. Null in the next range if all of it has this sig: then its own guest is the one."""
        near = F.when(F.lag(met_sig).over(turn) != F.col(sig), F.lag(met).over(turn)).otherwise(F.lag(other).over(turn))
        return near.alias(met)

    down, up = W.partitionBy("host").orderBy("deal"), W.partitionBy("host").orderBy(F.col("deal").desc())
    near = inner.select("host", "deal", outside(down, "first_sig", "last", "last_sig", "last_other"), outside(up, "last_sig", "first", "first_sig", "first_other"))
    near = near.select("deal", F.last("last", True).over(down).alias("before"), F.last("first", True).over(up).alias("behind"))
    found = near.select("deal", F.explode(F.array("before", "behind")).alias("place"))
    return found.where("place is not null").distinct()


SIZE = 16  # bytes of a digest


def _digest(text: str) -> bytes:
    return hashlib.blake2b(text.encode("utf-8", "surrogatepass"), digest_size=SIZE).digest()


def _row_key(page_id: str | None, url: str | None, html: str | None) -> bytes:
    return _digest("".join("-" if x is None else f"{len(x)}:{x}" for x in (page_id, url, html)))


def _digests(batches: Iterator[pd.DataFrame]) -> Iterator[pd.DataFrame]:
    for pdf in batches:
        keys = [_row_key(*r) for r in pdf[["page_id", "url", "html"]].itertuples(index=False)]
        pdf["lines"] = [b"".join(map(_digest, page_blocks(h)[0])) for h in pdf["html"]]
        yield pdf.drop(columns="html").assign(key=keys)[["key", "page_id", "url", "lines"]]


def _texts(batches: Iterator[pd.DataFrame]) -> Iterator[pd.DataFrame]:
    for pdf in batches:
        keys = [_row_key(*r) for r in pdf[["page_id", "url", "html"]].itertuples(index=False)]
        found = [page_blocks(h) for h in pdf["html"]]
        pdf = pdf.drop(columns="html").assign(key=keys, lines=[x for x, _, _ in found], inside=[i for _, i, _ in found], marked=[m for _, _, m in found])
        yield pdf[["key", "page_id", "url", "lines", "inside", "marked"]]


def own_lines(rows: DataFrame, group: int = GROUP) -> DataFrame:
    """key, own: for each line of a page, whether its nearest different page of the host lacks it. ``rows``: key, page_id, url, lines (their digests)."""

    def pair(pdf: pd.DataFrame) -> pd.DataFrame:
        pdf = pdf.sort_values("place")
        pdf["own"] = difference([(p, [x[i : i + SIZE] for i in range(0, len(x), SIZE)]) for p, x in zip(pdf["path"], pdf["lines"], strict=True)])
        return pdf.loc[~pdf["guest"], ["key", "own"]]

    rows = hand_over(rows, "page-lines")
    order = rows.select("key", host_of(F.col("url")).alias("host"), path_of(F.col("url")).alias("path"), "url", "page_id", "lines", F.unhex(F.md5("lines")).alias("sig"))
    keys = [F.col("host"), F.col("path"), F.col("url").asc_nulls_last(), F.col("page_id").asc_nulls_last(), F.col("sig"), F.col("key")]
    order = order.repartitionByRange(*keys).sortWithinPartitions(*keys).withColumn("place", F.monotonically_increasing_id())  # ascends in the whole order
    order = order.withColumn("deal", F.col("place") - F.col("place").bitwiseAND((1 << 33) - 1) % group)  # a range is named by its first place
    order = hand_over(order.select("key", "host", "path", "sig", "lines", "place", "deal"), "page-order")
    release(rows)
    placed = order.select("key", "host", "path", "lines", "place", "deal", F.lit(False).alias("guest"))
    guests = placed.drop("deal", "guest").join(_guests(order.select("host", "place", "deal", "sig")), "place").withColumn("guest", F.lit(True))
    return placed.unionByName(guests).groupBy("host", "deal").applyInPandas(pair, "key binary, own array<boolean>")


def extract_text(pages: DataFrame, page_id: str = "page_id", url: str = "url", html: str = "html", group: int = GROUP) -> DataFrame:
    """page_id, url, text, marked (whether the page marks its article), own, restored, left_out (numbers of lines: own by differencing, shared but
    in the marked article, own but outside it)."""
    rows = pages.select(F.col(page_id).cast("string").alias("page_id"), F.col(url).alias("url"), F.col(html).alias("html"))
    own = own_lines(rows.mapInPandas(_digests, "key binary, page_id string, url string, lines binary"), group)
    own = own.groupBy("key").agg(F.first("own").alias("differs"))  # rows that are equal in all have one outcome
    texts = rows.mapInPandas(_texts, "key binary, page_id string, url string, lines array<string>, inside array<boolean>, marked boolean")
    again = F.when(F.size("differs") == F.size("lines"), F.col("differs")).otherwise(F.raise_error(F.lit("pages gave other rows when read again")).cast("array<boolean>"))
    got = texts.join(own, "key", "left").withColumn("differs", again)
    differs, inside, marked = (lambda i: F.get("differs", i)), (lambda i: F.get("inside", i)), F.col("marked")
    parts = {"own": differs, "restored": lambda i: ~differs(i) & marked & inside(i), "left_out": lambda i: differs(i) & marked & ~inside(i)}
    kept = F.filter("lines", lambda _, i: (differs(i) | parts["restored"](i)) & ~parts["left_out"](i))
    number = lambda f: F.size(F.filter("lines", lambda _, i: f(i)))
    counts = [number(f).alias(name) for name, f in parts.items()]
    return got.select(F.col("page_id").cast(pages.schema[page_id].dataType).alias("page_id"), "url", F.array_join(kept, " ").alias("text"), "marked", *counts)


def query(spark: SparkSession, sf_dir: str) -> DataFrame:
    out = extract_text(table(spark, sf_dir, "pages"))
    return out.select("page_id", "url", "text", F.char_length("text").cast("long").alias("n_chars"), "own", "restored", "left_out")


ORACLE_SQL = None  # tests hold the rows against planted pages and a plain LCS
