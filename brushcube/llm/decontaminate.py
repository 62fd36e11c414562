"""Benchmark decontamination by a prefix-filtered set join. DataFrame functions only.

A window is 13 consecutive words of an item (all its words, if it has fewer but not none). A window can occur in a document only
if its rarest word does: words are ordered by rarity, that one word is the window's prefix, and only document
words that may be some window's prefix become candidates (a filter of FILTER_BITS tells, whatever the number of items; it never leaves one out,
and what it lets through in vain meets no window). A candidate carries its neighbourhood, joins the windows
on the prefix word, passes length and positional bounds (the window must lie inside the document) and is
then compared word for word. The hit positions of a document are the union of its occurrences.

Rarity is counted over all items; ties go to the longer word, then to the word order. It steers cost only.

Defined results: null or empty texts have no words, no hits and are not contaminated; items without words
have no window; equal items all count; repeated documents are judged each on its own; other columns
are kept (but for the operator's own names). Documents are never grouped by content: every row travels under its own row number.
"""

from __future__ import annotations

from collections.abc import Callable

from pyspark.sql import Column, DataFrame, SparkSession
from pyspark.sql import Window as W
from pyspark.sql import functions as F

from .common import LETTER_WORD, ascii_lower, table, words_of

WINDOW = 13
#: Log2 of the bits of the filter of prefix words: 128 KB, whatever the items.
FILTER_BITS = 20
#: Windows are broadcast up to so many rows (about 150 bytes each); beyond, both sides are shuffled.
BROADCAST_WINDOWS = 100_000


def item_windows(items: DataFrame, item_id: str = "item_id", text: str = "text", width: int = WINDOW) -> DataFrame:
    """Distinct windows: win_words, win_size, prefix (rarest word), offset (its first place), items."""
    words = items.select(F.col(item_id).cast("string").alias("item"), words_of(ascii_lower(F.col(text)), LETTER_WORD).alias("w")).where(F.size("w") > 0)
    starts = F.sequence(F.lit(1), F.greatest(F.size("w") - width + 1, F.lit(1)))
    wins = words.select("item", "w", F.explode(starts).alias("at")).select("item", F.slice("w", F.col("at"), F.lit(width)).alias("win_words"))
    wins = wins.groupBy("win_words").agg(F.collect_set("item").alias("items"))
    counts = words.select(F.explode("w").alias("word")).groupBy("word").agg(F.count("*").alias("n"))
    ranked = wins.select("win_words", F.explode(F.array_distinct("win_words")).alias("word")).join(counts, "word")
    rarest = F.min(F.struct(F.col("n"), (-F.char_length("word")).alias("short"), F.col("word"))).alias("rarest")
    prefix = ranked.groupBy("win_words").agg(rarest).select(F.col("win_words").alias("pw"), F.col("rarest.word").alias("prefix"))
    out = wins.join(prefix, F.col("win_words") == F.col("pw"))
    return out.select("win_words", F.size("win_words").alias("win_size"), "prefix", F.array_position("win_words", F.col("prefix")).cast("int").alias("offset"), "items")


def _place(word: Column) -> Column:
    return F.shiftrightunsigned(F.xxhash64(word), 64 - FILTER_BITS)


def prefix_filter(windows: DataFrame) -> Callable[[Column], Column]:
    """word -> whether it may be a prefix. The bits are one literal of 64-bit numbers, of fixed size: subqueries can't stand in functions over arrays."""
    p = windows.select(_place(F.col("prefix")).alias("p"))
    words = p.groupBy(F.shiftright("p", 6).alias("id")).agg(F.bit_or(F.expr("shiftleft(1L, cast(p % 64 as int))")).alias("b"))
    numbers = ["0"] * (1 << (FILTER_BITS - 6))
    for r in words.collect():  # at most one row a number
        numbers[r["id"]] = str(r["b"])
    bits = F.split(F.lit(",".join(numbers)), ",").cast("array<bigint>")  # folded to a literal array by the optimiser
    return lambda w: F.getbit(F.get(bits, F.shiftright(_place(w), 6).cast("int")), (_place(w) % 64).cast("int")) == 1


def occurrences(docs: DataFrame, windows: DataFrame, text: str = "text", width: int = WINDOW) -> DataFrame:
    """One row per document row: the kept columns, n_words, places (start, size, items of each occurrence)."""
    small = windows.limit(BROADCAST_WINDOWS + 1).count() <= BROADCAST_WINDOWS
    keep = [c for c in docs.columns if c != text]
    # not one projection: the word array is an input of the next, so it is made once per row
    rows = docs.select(F.monotonically_increasing_id().alias("row_no"), *keep, words_of(ascii_lower(F.col(text)), LETTER_WORD).alias("doc_words"))
    wanted = prefix_filter(windows)
    near = lambda i: F.struct(  # noqa: E731  1-based place, where the cut-out begins, and the cut-out
        (i + 1).alias("at"), F.greatest(i + 2 - width, F.lit(1)).alias("from"), F.slice(F.col("doc_words"), F.greatest(i + 2 - width, F.lit(1)), F.lit(2 * width - 1)).alias("around"))
    cands = F.array_compact(F.transform("doc_words", lambda w, i: F.when(wanted(w), near(i))))
    rows = rows.select("row_no", *keep, F.size("doc_words").cast("long").alias("n_words"), cands.alias("cands"))
    found = rows.select("row_no", "n_words", *keep, F.explode_outer("cands").alias("c"))
    found = found.withColumn("token", F.element_at("c.around", F.col("c.at") - F.col("c.from") + 1))
    side = F.broadcast(windows) if small else windows
    start = F.col("c.at") - F.col("offset") + 1
    fits = (start >= 1) & (start + F.col("win_size") - 1 <= F.col("n_words"))
    same = F.slice("c.around", F.greatest(start - F.col("c.from") + 1, F.lit(1)), F.col("win_size")) == F.col("win_words")
    hits = found.join(side, (F.col("token") == F.col("prefix")) & fits & same, "left")
    place = F.when(F.col("win_size").isNotNull(), F.struct(start.cast("int").alias("start"), F.col("win_size").alias("size"), "items"))
    return hits.groupBy("row_no").agg(*[F.first(c).alias(c) for c in (*keep, "n_words")], F.collect_list(place).alias("places"))


def decontaminate(docs: DataFrame, items: DataFrame, text: str = "text", width: int = WINDOW) -> DataFrame:
    """``docs`` without its text, with n_words, n_hit, n_items, items_sha256, item_ids, hit_places and contaminated."""
    own = ("n_words", "n_hit", "n_items", "items_sha256", "item_ids", "hit_places", "contaminated", "places", "row_no", "doc_words", "cands")
    docs = docs.drop(*[c for c in own if c in docs.columns])
    found = occurrences(docs, item_windows(items, width=width), text, width)
    covered = F.array_distinct(F.flatten(F.transform("places", lambda p: F.sequence(p["start"], p["start"] + p["size"] - 1))))
    ids = F.array_sort(F.array_distinct(F.flatten(F.transform("places", lambda p: p["items"]))))
    found = found.withColumns({"hit_places": covered, "item_ids": ids})
    found = found.withColumns({"n_hit": F.size("hit_places").cast("long"), "n_items": F.size("item_ids").cast("long"), "items_sha256": F.sha2(F.array_join("item_ids", ","), 256)})
    return found.withColumn("contaminated", (F.col("n_hit") > 0) & (20 * F.col("n_hit") >= F.col("n_words"))).drop("places", "row_no")


def query(spark: SparkSession, sf_dir: str) -> DataFrame:
    docs = table(spark, sf_dir, "documents").select("doc_id", "text")
    out = decontaminate(docs, table(spark, sf_dir, "benchmark"))
    return out.select("doc_id", "n_words", "n_hit", "n_items", "items_sha256", "contaminated")


_WORDS = "coalesce(regexp_extract_all(translate(text, 'ABCDEFGHIJKLMNOPQRSTUVWXYZ', 'abcdefghijklmnopqrstuvwxyz'), '[^\\x00-\\x2F\\x3A-\\x60\\x7B-\\x7F]+'), [])"
ORACLE_SQL = f"""
WITH iw AS (SELECT item_id::VARCHAR AS item, {_WORDS} AS w FROM benchmark),
wins AS (SELECT DISTINCT item, w[s:s + least(13, len(w)) - 1] AS win
         FROM (SELECT item, w, unnest(generate_series(1, greatest(len(w) - 12, 1))) AS s FROM iw WHERE len(w) > 0)),
sizes AS (SELECT DISTINCT len(win) AS n FROM wins),
d AS (SELECT row_number() OVER () AS rn, doc_id, {_WORDS} AS w FROM documents),
dw AS (SELECT rn, s, n, w[s:s + n - 1] AS win
       FROM (SELECT rn, w, n, unnest(generate_series(1, len(w) - n + 1)) AS s FROM d, sizes WHERE len(w) >= n)),
m AS (SELECT rn, s, n, item FROM dw JOIN wins USING (win)),
h AS (SELECT rn, count(DISTINCT p) AS n_hit FROM (SELECT rn, unnest(generate_series(s, s + n - 1)) AS p FROM m) GROUP BY rn),
i AS (SELECT rn, count(DISTINCT item) AS n_items, string_agg(DISTINCT item, ',' ORDER BY item) AS ids FROM m GROUP BY rn)
SELECT doc_id, len(w)::BIGINT AS n_words, coalesce(n_hit, 0)::BIGINT AS n_hit, coalesce(n_items, 0)::BIGINT AS n_items,
       sha256(coalesce(ids, '')) AS items_sha256, coalesce(n_hit, 0) > 0 AND 20 * coalesce(n_hit, 0) >= len(w) AS contaminated
FROM d LEFT JOIN h USING (rn) LEFT JOIN i USING (rn)
"""
