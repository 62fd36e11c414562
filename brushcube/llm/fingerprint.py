"""Document fingerprints: threshold-scaled sketches. DataFrame functions only.

A fingerprint keeps every 5-word shingle hash below a fixed fraction of the hash range (1/SCALE), of documents of any length, so sketches of unequal
documents are samples by one rule: they merge by union and give containment as well as likeness.

The string is ``<scale>:<hash>,<hash>,...`` with hexadecimal hashes in ascending order; a text without words has ``0:``.

Defined results: a null text is an empty one; a text of fewer than five words is one shingle. Two texts without words are alike (1.0). Where no hash of
either text was kept and one of them has words, nothing is known of them and the likeness is 0.0 (short texts; expected of a share of (1 - 1/SCALE)^n of
those with n shingles). Repeated rows stand in the order next to each other (ties of the id by text) and each is edited by its neighbour; a null id comes last in the descending
order; ids are numbers; extra columns of the input are not read.

The next document is found without ordering all rows in one task: ids fall into ranges of about RANGE rows, each is
ordered on its own, and a copy of the first row of each range stands as a guest behind the range above it. Ids may be spread unevenly: a range of
equal width that holds too many rows is cut again between its own least and greatest ids, LEVELS times.
"""

from __future__ import annotations

from pyspark.sql import Column, DataFrame, SparkSession
from pyspark.sql import Window as W
from pyspark.sql import functions as F

from .common import SPACED_WORD, table, words_of

SHINGLE, SCALE, RANGE, LEVELS = 5, 4, 4096, 4
#: Ranges' first ids (three numbers each) are broadcast up to so many ranges; beyond, Spark joins by shuffling.
BROADCAST_HEADS = 100_000


def kept(h: Column, scale: int = SCALE) -> Column:
    """Whether a hash, read as an unsigned number, lies in the first 1/scale of the range."""
    return F.shiftrightunsigned(h, 64 - (scale.bit_length() - 1)) == 0


def sketch(words: Column, size: int = SHINGLE, scale: int = SCALE) -> Column:
    """Sorted distinct hashes of the shingles of a word array that lie below the threshold."""
    n = F.size(words)
    grams = F.transform(F.sequence(F.lit(0), n - size), lambda i: F.xxhash64(*[words[i + k] for k in range(size)]))
    whole = F.array(F.xxhash64(F.array_join(words, " ")))
    every = F.when(n >= size, grams).when(n > 0, whole).otherwise(F.array().cast("array<bigint>"))
    return F.array_sort(F.array_distinct(F.filter(every, lambda h: kept(h, scale)) if scale > 1 else every))


def text_of(scale: Column, hashes: Column) -> Column:
    return F.concat(scale.cast("string"), F.lit(":"), F.array_join(F.transform(hashes, F.hex), ","))


def likeness(a: Column, a_scale: Column, b: Column, b_scale: Column) -> Column:
    """Jaccard estimate of two sketches."""
    union = F.size(F.array_union(a, b))
    return F.when(union > 0, F.size(F.array_intersect(a, b)) / union).otherwise(F.when((a_scale == 0) & (b_scale == 0), 1.0).otherwise(0.0))


def containment(a: Column, b: Column) -> Column:
    """Share of a's shingles that b has, estimated."""
    return F.when(F.size(a) > 0, F.size(F.array_intersect(a, b)) / F.size(a)).otherwise(0.0)


def add_fingerprint(df: DataFrame, text: Column, prefix: str, scale: int = SCALE) -> DataFrame:
    """``<prefix>hashes`` (array) and ``<prefix>scale`` (0 of texts without words) of a text column, each made once per row."""
    df = df.withColumn("fp_words", words_of(F.lower(text), SPACED_WORD))
    return df.withColumns({f"{prefix}scale": F.when(F.size("fp_words") > 0, scale).otherwise(0), f"{prefix}hashes": sketch(F.col("fp_words"), scale=scale)}).drop("fp_words")


def _width(lo: Column, hi: Column, n: Column) -> Column:
    return F.greatest(F.lit(1), F.ceil((hi - lo + 1) * RANGE / n)).cast("double")


def in_ranges(docs: DataFrame, doc_id: str = "doc_id", text: str = "text") -> DataFrame:
    """``docs`` with span and guest: each range of ids, and behind it (guest) a copy of the first row of the range below. Spans are arrays of LEVELS numbers, in the order of ids."""
    ids = docs.select(F.col(doc_id).cast("double").alias("id"))
    edge = ids.agg(F.min("id").alias("lo"), F.max("id").alias("hi"), F.count("*").alias("n")).first()
    lo, hi, n = edge["lo"] or 0.0, edge["hi"] or 0.0, max(1, edge["n"])
    here = lambda id, lo, width: F.coalesce(F.floor((id - lo) / width), F.lit(-1)).cast("long")
    first = here(F.col(doc_id).cast("double"), F.lit(lo), _width(F.lit(lo), F.lit(hi), F.lit(n)))
    rows, deep = docs.select(doc_id, text, F.array(first).alias("span")), ids.select("id", F.array(here(F.col("id"), F.lit(lo), _width(F.lit(lo), F.lit(hi), F.lit(n)))).alias("span"))
    for _ in range(1, LEVELS):  # ids only; a few numbers per overfull range
        full = deep.groupBy("span").agg(F.min("id").alias("lo"), F.max("id").alias("hi"), F.count("*").alias("n")).where((F.col("n") > 4 * RANGE) & (F.col("hi") > F.col("lo")))
        full = full.select(F.col("span").alias("of"), F.col("lo"), _width(F.col("lo"), F.col("hi"), F.col("n")).alias("width"))
        cuts = full.limit(BROADCAST_HEADS + 1).collect()
        finer = lambda df, id: df.join(full if len(cuts) > BROADCAST_HEADS else F.broadcast(full), F.col("span") == F.col("of"), "left").withColumn(  # noqa: B023, E731
            "span", F.concat("span", F.array(F.when(F.col("of").isNull(), 0).otherwise(here(id, F.col("lo"), F.col("width")))))).drop("of", "lo", "width")
        if not cuts:
            break
        rows, deep = finer(rows, F.col(doc_id).cast("double")), finer(deep, F.col("id"))
    heads = rows.groupBy("span").agg(F.max(doc_id).alias("head_id"))
    turn = W.orderBy(F.col("span").desc())  # one row per range of about RANGE documents
    heads = heads.withColumns({"head_span": F.col("span"), "upper": F.coalesce(F.lag("span").over(turn), F.min("span").over(W.partitionBy()))}).drop("span")
    if n // RANGE * 4 + 2 <= BROADCAST_HEADS:
        heads = F.broadcast(heads)
    found = rows.join(heads, F.col("span").eqNullSafe(F.col("head_span")) & F.col(doc_id).eqNullSafe(F.col("head_id")))
    guests = found.groupBy("upper", doc_id).agg(F.max(text).alias(text)).select(doc_id, text, F.col("upper").alias("span"), F.lit(True).alias("guest"))
    return rows.withColumn("guest", F.lit(False)).unionByName(guests)


def fingerprints(docs: DataFrame, doc_id: str = "doc_id", text: str = "text") -> DataFrame:
    """doc_id, text, hashes, scale and next_text, next_hashes, next_scale: of the next document by descending id, cyclically."""
    docs = docs.select(F.col(doc_id).alias("doc_id"), F.coalesce(text, F.lit("")).alias("text"))
    rows = add_fingerprint(in_ranges(docs), F.col("text"), "")
    order = W.partitionBy("span").orderBy("guest", F.col("doc_id").desc_nulls_last(), F.col("text").desc())
    # column by column: a struct would be built below the exchange and travel beside its parts
    return rows.withColumns({f"next_{c}": F.lead(c).over(order) for c in ("text", "hashes", "scale")}).where(~F.col("guest")).drop("guest", "span")


def query(spark: SparkSession, sf_dir: str) -> DataFrame:
    docs = fingerprints(table(spark, sf_dir, "documents"))
    n = F.char_length("text")
    cut = F.floor(n / 3).cast("int")
    edited = F.concat(F.substring(F.col("text"), F.lit(1), n - cut), F.substring(F.col("next_text"), F.lit(1), cut))
    docs = docs.select("doc_id", n.cast("long").alias("n_chars"), edited.alias("edited"), "hashes", "scale", "next_hashes", "next_scale")
    docs = add_fingerprint(docs, F.col("edited"), "edited_")
    f = [F.col(c) for c in ("hashes", "scale", "edited_hashes", "edited_scale", "next_hashes", "next_scale")]
    return docs.select(
        "doc_id", "n_chars", F.sha2("edited", 256).alias("edited_sha256"), text_of(f[1], f[0]).alias("fingerprint"), text_of(f[3], f[2]).alias("edited_fingerprint"),
        likeness(f[0], f[1], f[2], f[3]).alias("near_edited"), likeness(f[0], f[1], f[4], f[5]).alias("near_next"))


ORACLE_SQL = None  # the hashes are Spark's; tests hold the rows against a plain Python version
