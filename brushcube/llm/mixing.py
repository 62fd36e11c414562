"""Mixing sources to target weights by Pareto order sampling. DataFrame functions only.

Targets: all sources share ``share`` times the words of the corpus by weight; a source stops at ``cap``
times its own words and the excess is dealt to the others by weight until none is above. With d documents'
expected copies e = target / source words, floor(e) whole copies are certain, and the fraction pi = e - floor(e) is
sampled: a document gets the rank q = (u / (1 - u)) / (pi / (1 - pi)), u a uniform number made from its id, and the
lowest ranks are taken until their words are nearest to what is left of the target. So a source's size is fixed, its
documents' probabilities are those asked for, and reruns agree.

Cost: no step holds a source's documents together. Ranks fall into narrow bins, bins are summed per source
(map-side first), the bin in which the target is crossed is found on those sums, and only that bin's
documents are ordered.

Defined results: a null text has size 0; sources are ordered by code point, a null source comes last and is a
source like others; rows with the same id and source have the same rank and are taken together;
a null id is hashed as an empty string; a source without words has target 0 and nothing is taken; an empty table
gives an empty result. Columns of the input are kept; the operator's own (size, source_size, target, copies, taken)
replace columns of the same names.
"""

from __future__ import annotations

from pyspark.sql import Column, DataFrame, SparkSession
from pyspark.sql import Window as W
from pyspark.sql import functions as F

from .common import SPACED_WORD, hand_over, release, table

#: Repeating weights of the contract, the mix's size against the corpus and the most copies of a source.
WEIGHTS, SHARE, CAP = (3, 1, 2), 1.5, 2.0
#: Bins of ranks per unit of ln(q): about 1/4096 of a source's documents in the fullest bin.
BINS = 1024


def word_count(text: Column) -> Column:
    return F.coalesce(F.regexp_count(text, F.lit(SPACED_WORD)), F.lit(0)).cast("long")


def source_targets(sizes: DataFrame, weights=WEIGHTS, share: float = SHARE, cap: float = CAP) -> DataFrame:
    """(source, source_size) -> target. One row per source, so one small ordered pass over the sources."""
    if cap < share:
        raise ValueError("sources can't hold the mix: cap is below share")
    ordered = W.orderBy(F.col("source").asc_nulls_last())
    pick = F.element_at(F.array(*[F.lit(int(w)) for w in weights]), (F.pmod(F.row_number().over(ordered) - 1, F.lit(len(weights))) + 1).cast("int"))
    s = sizes.withColumn("weight", pick)
    total, every = F.sum("source_size").over(W.partitionBy()), F.sum("weight").over(W.partitionBy())
    # Sources reach their caps in the order of cap / weight; the first that stays below its cap sets the level.
    line = W.orderBy((F.col("source_size") / F.col("weight")).asc(), F.col("source").asc_nulls_last())
    before = line.rowsBetween(W.unboundedPreceding, -1)
    s = s.withColumns({"total": total, "full": F.coalesce(F.sum("source_size").over(before), F.lit(0)), "open": every - F.coalesce(F.sum("weight").over(before), F.lit(0))})
    level = (F.lit(share) * F.col("total") - F.lit(cap) * F.col("full")) / F.col("open")
    s = s.withColumn("level", level).withColumn("fits", F.col("level") * F.col("weight") <= F.lit(cap) * F.col("source_size"))
    s = s.withColumn("place", F.row_number().over(line))
    s = s.withColumn("common", F.min(F.when(F.col("fits"), F.struct("place", "level"))).over(W.partitionBy()).getField("level"))
    return s.select("source", "source_size", F.least(F.lit(cap) * F.col("source_size"), F.coalesce(F.col("common"), F.lit(float("inf"))) * F.col("weight")).alias("target"))


def uniform(key: Column) -> Column:
    """A number in (0, 1) from the key: 52 bits of its MD5."""
    return (F.conv(F.substring(F.md5(key), 1, 13), 16, 10).cast("long").cast("double") + 0.5) / float(1 << 52)


def sampling_plan(sized: DataFrame, weights=WEIGHTS, share: float = SHARE, cap: float = CAP) -> DataFrame:
    """(source, size, key, u) -> per source: source_size, target, whole copies, pi and the last rank (q, key) taken."""
    targets = source_targets(sized.groupBy("source").agg(F.sum("size").alias("source_size")), weights, share, cap)
    e = F.when(F.col("source_size") > 0, F.col("target") / F.col("source_size")).otherwise(F.lit(0.0))
    targets = targets.withColumn("whole", F.floor(e)).withColumn("pi", F.when(F.col("source_size") > 0, (F.col("target") - F.col("whole") * F.col("source_size")) / F.col("source_size")).otherwise(0.0))
    targets = targets.withColumn("left", F.col("pi") * F.col("source_size"))
    # Sources' facts are few and small; the join picks broadcast or shuffle by their size.
    ranked = sized.join(targets.select(F.col("source").alias("src"), "pi", "left"), F.col("source").eqNullSafe(F.col("src"))).where("pi > 0")
    ranked = ranked.withColumn("q", rank(F.col("u"), F.col("pi"))).withColumn("bin", F.floor(F.log("q") * BINS))
    bins = ranked.groupBy("source", "bin").agg(F.sum("size").alias("words"), F.first("left").alias("left"))
    upto = F.sum("words").over(W.partitionBy("source").orderBy("bin"))
    bins = bins.withColumn("upto", upto).withColumn("before", F.col("upto") - F.col("words")).where("before < left and upto >= left")
    # bins without words cannot cross; the first crossing bin is the only one kept
    edge = ranked.join(bins.select(F.col("source").alias("bsrc"), F.col("bin").alias("bbin"), "before"), F.col("source").eqNullSafe(F.col("bsrc")) & (F.col("bin") == F.col("bbin")))
    edge = edge.groupBy("source", "q", "key").agg(F.sum("size").alias("words"), F.first("left").alias("left"), F.first("before").alias("before"))
    run = F.col("before") + F.sum("words").over(W.partitionBy("source").orderBy("q", "key"))
    edge = edge.withColumn("run", run)
    # Nearest end: after the document that crosses, or just before it.
    edge = edge.withColumn("prior", F.col("run") - F.col("words")).where("prior < left")
    edge = edge.withColumn("take", (F.col("run") - F.col("left")) <= (F.col("left") - F.col("prior")))
    cut = edge.where("run < left or take").groupBy("source").agg(F.max(F.struct("q", "key")).alias("last"))
    first = edge.groupBy("source").agg(F.min(F.struct("q", "key")).alias("first"))
    cuts = first.join(cut.withColumnRenamed("source", "csrc"), F.col("source").eqNullSafe(F.col("csrc")), "left").select(F.col("source").alias("esrc"), "first", "last")
    plan = targets.join(cuts, F.col("source").eqNullSafe(F.col("esrc")), "left")
    return plan.select(F.col("source").alias("plan_source"), "source_size", "target", "whole", "pi", "first", "last")


def rank(u: Column, pi: Column) -> Column:
    return (u / (1 - u)) / (pi / (1 - pi))


def mix(docs: DataFrame, doc_id: str = "doc_id", text: str = "text", source: str = "source", weights=WEIGHTS, share: float = SHARE, cap: float = CAP) -> DataFrame:
    """``docs`` with size, source_size, target, copies and taken (words the mix takes, repeats counted)."""
    own = ("size", "source_size", "target", "copies", "taken")
    docs = docs.drop(*[c for c in own if c in docs.columns])
    key = F.md5(F.coalesce(F.col(doc_id).cast("string"), F.lit("")))
    seen = docs.select(F.col(source).alias("source"), word_count(F.col(text)).alias("size"), key.alias("key"), uniform(F.coalesce(F.col(doc_id).cast("string"), F.lit(""))).alias("u"))
    sizes = hand_over(seen, "mix-sizes")
    plan = hand_over(sampling_plan(sizes, weights, share, cap), "mix-plan")
    release(sizes)
    tag = {"size": word_count(F.col(text)), "mix_key": key, "mix_u": uniform(F.coalesce(F.col(doc_id).cast("string"), F.lit("")))}
    out = docs.withColumns(tag).join(plan, F.col(source).eqNullSafe(F.col("plan_source")))
    here = F.struct(rank(F.col("mix_u"), F.col("pi")).alias("q"), F.col("mix_key").alias("key"))
    # Ranks below the crossing bin's first document are in; within the bin, those up to the last taken.
    extra = (F.col("pi") > 0) & F.coalesce(here <= F.col("last"), here < F.col("first"), F.lit(False))
    copies = F.col("whole") + F.when(extra, 1).otherwise(0)
    out = out.withColumn("copies", copies.cast("long")).withColumn("taken", (F.col("size") * F.col("copies")).cast("long"))
    return out.select(*docs.columns, *own)


def query(spark: SparkSession, sf_dir: str) -> DataFrame:
    docs = table(spark, sf_dir, "documents").select("doc_id", "text", "source")
    return mix(docs).select("doc_id", "size", "source_size", "target", "taken")


ORACLE_SQL = """
WITH d AS (SELECT doc_id, source, coalesce(len(regexp_extract_all(text, '[^\\x20\\x09-\\x0D]+')), 0)::BIGINT AS size, md5(coalesce(doc_id::VARCHAR, '')) AS k FROM documents),
s0 AS (SELECT source, sum(size)::BIGINT AS s FROM d GROUP BY source),
s1 AS (SELECT *, CASE (row_number() OVER (ORDER BY source ASC NULLS LAST) - 1) % 3 WHEN 0 THEN 3 WHEN 1 THEN 1 ELSE 2 END AS w FROM s0),
s2 AS (SELECT *, sum(s) OVER () AS total, sum(w) OVER () AS every,
        coalesce(sum(s) OVER (ORDER BY s::DOUBLE / w, source NULLS LAST ROWS BETWEEN UNBOUNDED PRECEDING AND 1 PRECEDING), 0) AS full_s,
        coalesce(sum(w) OVER (ORDER BY s::DOUBLE / w, source NULLS LAST ROWS BETWEEN UNBOUNDED PRECEDING AND 1 PRECEDING), 0) AS full_w FROM s1),
s3 AS (SELECT *, (1.5::DOUBLE * total::DOUBLE - 2.0::DOUBLE * full_s::DOUBLE) / (every - full_w)::DOUBLE AS level FROM s2),
s4 AS (SELECT *, (SELECT level FROM s3 WHERE level * w <= 2.0::DOUBLE * s ORDER BY s::DOUBLE / w, source NULLS LAST LIMIT 1) AS common FROM s3),
s5 AS (SELECT source, s, least(2.0::DOUBLE * s, coalesce(common, 'inf'::DOUBLE) * w) AS target FROM s4),
s6 AS (SELECT *, CASE WHEN s > 0 THEN floor(target / s)::BIGINT ELSE 0 END AS whole FROM s5),
s7 AS (SELECT *, CASE WHEN s > 0 THEN (target - whole * s) / s ELSE 0 END AS pi FROM s6),
q0 AS (SELECT d.doc_id, d.source, d.size, d.k, s7.s, s7.target, s7.whole, s7.pi, s7.pi * s7.s AS lft,
        (((('0x' || substr(k, 1, 13))::BIGINT)::DOUBLE + 0.5::DOUBLE) / 4503599627370496.0::DOUBLE) AS u
       FROM d JOIN s7 ON d.source IS NOT DISTINCT FROM s7.source),
q1 AS (SELECT *, (u / (1 - u)) / (pi / (1 - pi)) AS q FROM q0),
q2 AS (SELECT *, sum(size) OVER (PARTITION BY source ORDER BY q, k RANGE BETWEEN UNBOUNDED PRECEDING AND CURRENT ROW) AS run,
        sum(size) OVER (PARTITION BY source, q, k) AS own FROM q1)
SELECT doc_id, size, s AS source_size, target,
       (size * (whole + CASE WHEN pi > 0 AND run - own < lft AND (run < lft OR run - lft <= lft - (run - own)) THEN 1 ELSE 0 END))::BIGINT AS taken
FROM q2
"""
