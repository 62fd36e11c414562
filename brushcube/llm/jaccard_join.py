"""N-gram Jaccard join by universe partition and pigeonhole.

A document is the set of its 5-word shingles (64-bit hashes); documents with equal sets are one class and are never paired. Two sets of sizes
a <= b with Jaccard >= 3/4 differ in at most H = (a + b) div 7 shingles. The hash universe is cut into m segments, m set by the
band of the larger set's size (bands grow by 4/3, so a partner is in the same band or in the one below). If the sets differ in at most H shingles, they cannot differ in
H + 1 segments: of any H + 1 segments that the larger set picks, one subset is equal in both. Segments that a set can't pick (empty ones)
are made up for by segments counted twice: those also meet through one-deletion neighbourhoods, so they differ by two shingles if they don't meet.

1. Every set emits the hashes of its segment subsets (own band, and the band above where it may be the smaller partner)
   and of the one-deletion neighbourhoods of the segments allowed to have them, packed into one binary block per target partition.
   In the bands of the smallest sets every shingle is a segment of its own.
2. Each partition cuts its blocks into slices of the hash range, lets Spark sort the slices (which spills), and reports slice by slice the hashes
   that two classes share, with the size of the group. So a Python worker never holds more than some slices, whatever the partition holds.
3. Allocation by cost: segments nobody shares are free; what is missing to H + 1 is taken from the set's smallest groups. Sets with H + 1
   unshared segments have no partner and drop out.
4. Leader rounds: in each group, classes are compared with its best connected class only; verified links are contracted.
   Groups of near copies shrink to one component without their pairs being made.
5. What is left between different components is enumerated and verified, every link exactly on the whole sets.

A set whose segments can't reach H + 1 even with deletions (it takes very uneven hashes; about one in a million) is compared through the
shingle prefix any partner must share: one more scan, behind a filter of fixed size over the shingles and bands asked for. Nothing is capped, dropped or sampled.

A class is a set's 128-bit digest. Hashes travel with its first half; where two sets share that half, they get numbers of their own before anything is compared.

Defined results: null and wordless texts have no shingles and stay alone; fewer words than five make one shingle; repeated rows and
equal texts are one component; a null id never names a component that has other ids; extra columns are not read.
"""

from __future__ import annotations

from collections.abc import Iterator
from dataclasses import dataclass

import numpy as np
import pyarrow as pa
from pyspark.sql import Column, DataFrame, SparkSession
from pyspark.sql import Window as W
from pyspark.sql import functions as F

from .common import give_back, hand_over, part_of, release, table
from .components import components

SHINGLE = 5
OWN, OWN_DELETED, BELOW, BELOW_DELETED = range(4)
_K = [np.uint64(k) for k in (0x9E3779B97F4A7C15, 0xC2B2AE3D27D4EB4F, 0x165667B19E3779F9, 0xFF51AFD7ED558CCD, 0xC4CEB9FE1A85EC53)]
#: Groups of more classes, or of more shingles together, are compared in blocks of so many.
JOINED, BLOCK, TOKENS = 32, 512, 400_000
BITS = 25  # log2 of the bits of a scan filter: 4 MB, whatever the data
#: Hashes that a signing task holds before it sends them, that a slicing task cuts at once, and that are sorted together; rows (of texts, sets or blocks) that go to a Python worker at once.
FLUSH, CUT, SORTED, BATCH = 1_000_000, 250_000, 500_000, 128


def bands(largest: int) -> np.ndarray:
    """Upper ends of the size bands, up to the one that holds ``largest`` and one above."""
    ends = [1]
    while ends[-1] < largest:
        ends.append(max(ends[-1] + 1, ends[-1] * 4 // 3))
    ends.append(max(ends[-1] + 1, ends[-1] * 4 // 3))
    return np.array(ends, dtype=np.int64)


@dataclass(frozen=True)
class Scheme:
    """How bands are cut: share and number of segments beyond those needed, sets up to which all segments have deletions, and up to which every shingle is a segment."""

    slack: float = 1.15
    spare: int = 2
    small: int = 64
    singles: int = 16

    def segments(self, ends: np.ndarray) -> np.ndarray:
        """Segments of each band: enough for H + 1 picks, and some to choose from. Up to ``singles`` as many as there are 32-bit hashes."""
        return np.where(ends <= self.singles, 1 << 32, np.ceil(self.slack * (2 * ends // 7 + 1)).astype(np.int64) + self.spare)

    def deletable(self, ends: np.ndarray, m: np.ndarray) -> np.ndarray:
        """How many (leading) segments of each band have one-deletion neighbourhoods."""
        return np.where(ends <= self.singles, 0, np.where(ends <= self.small, m, m // 12 + 1 if self.small else 0 * m))


def _mix(x: np.ndarray) -> np.ndarray:
    x = (x ^ (x >> np.uint64(33))) * _K[3]
    x = (x ^ (x >> np.uint64(33))) * _K[4]
    return x ^ (x >> np.uint64(33))


def shingle_set(text: str | None, size: int = SHINGLE) -> np.ndarray:
    """Sorted distinct hashes of the shingles of a whole text (A-Z lower-cased, ASCII white space between words)."""
    import xxhash

    words = text.encode().lower().split() if text else []
    if not words:
        return np.empty(0, np.uint64)
    h = np.fromiter(map(xxhash.xxh64_intdigest, words), np.uint64, len(words))
    with np.errstate(over="ignore"):
        if len(h) <= size:
            out = np.full(1, len(h), np.uint64)
            for w in h:
                out = _mix(out * _K[0] + w)
            return out
        out = np.full(len(h) - size + 1, size, np.uint64)
        for k in range(size):
            out = _mix(out * _K[0] + h[k : len(h) - size + 1 + k])
    return np.unique(out)


def class_of(s: np.ndarray) -> tuple[int, int]:
    """A signed 128-bit digest of a set, as two halves."""
    import xxhash

    d = xxhash.xxh3_128_intdigest(s.tobytes())
    return (d >> 64) - 2**63, (d & (2**64 - 1)) - 2**63


def signatures(sets: list[np.ndarray], band: np.ndarray, m: np.ndarray, d: np.ndarray):
    """Of many non-empty sets in one scheme each (band[i]): (row, subset hash) for whole and for thinned segments, and per
    set the numbers of filled segments and of deletable segments with two shingles or more."""
    sizes = np.fromiter(map(len, sets), np.int64, len(sets))
    h, row = np.concatenate(sets), np.repeat(np.arange(len(sets)), sizes)
    with np.errstate(over="ignore"):
        seg = ((h >> np.uint64(32)) * m[band][row].astype(np.uint64)) >> np.uint64(32)  # rises with h: segments are runs
        start = np.flatnonzero(np.r_[True, (seg[1:] != seg[:-1]) | (row[1:] != row[:-1])])
        count = np.diff(np.r_[start, len(h)])
        mixed = _mix(h * _K[1])
        total = np.add.reduceat(mixed, start)
        at = row[start]
        place = band[at].astype(np.uint64) * _K[2] + seg[start] * _K[0]
        whole = _mix(total + place)
        open_ = (seg[start].astype(np.int64) < d[band][at]) & (count >= 2)
        run = np.repeat(np.arange(len(start)), count)
        thin = open_[run]
        thinned = _mix(total[run[thin]] - mixed[thin] + place[run[thin]])
    filled = np.bincount(at, minlength=len(sets))
    return (at, whole), (row[thin], thinned), filled, np.bincount(at[open_], minlength=len(sets))


def _pack(parts: int, cls: np.ndarray, sig: np.ndarray) -> Iterator[tuple]:
    """(part, classes, counts, hashes): one row per target partition; the low 40 bits of hashes travel, the high ones say the partition."""
    part = ((sig >> np.uint64(40)) * np.uint64(parts) >> np.uint64(24)).astype(np.int64)
    order = np.lexsort((cls, part))
    part, cls, sig = part[order], cls[order], sig[order]
    edge = np.flatnonzero(np.r_[True, part[1:] != part[:-1]]) if len(part) else part
    for a, b in zip(edge, np.r_[edge[1:], len(part)]):
        c, s = cls[a:b], sig[a:b]
        first = np.flatnonzero(np.r_[True, (c[1:] != c[:-1])])
        counts = np.diff(np.r_[first, b - a])
        if counts.max() > 65535:  # a run's length takes two bytes
            first = np.unique(np.r_[first, np.concatenate([np.arange(f, f + n, 65535) for f, n in zip(first, counts)])])
            counts = np.diff(np.r_[first, b - a])
        low = np.ascontiguousarray(s.astype("<u8")).view(np.uint8).reshape(-1, 8)[:, :5]
        yield int(part[a]), c[first].tobytes(), counts.astype("<u2").tobytes(), low.tobytes()


_DOC = [("doc_id", pa.int64()), ("tag", pa.int64()), ("n", pa.int64()), ("cls", pa.int64()), ("check", pa.int64()), ("filled", pa.int32()), ("spare", pa.int32())]
_PACKED = pa.schema([("part", pa.int32()), ("role", pa.int32()), ("classes", pa.binary()), ("counts", pa.binary()), ("hashes", pa.binary()), *_DOC])
_SLICED = pa.schema([("slice", pa.int32()), ("part", pa.int32()), ("classes", pa.binary()), ("roles", pa.binary()), ("hashes", pa.binary()), *_DOC])
_REPORT = pa.schema([*_DOC, ("sig", pa.int64()), ("role", pa.int32()), ("size", pa.int64()), ("report", pa.bool_())])


def _ddl(schema: pa.Schema) -> str:
    names = {"int32": "int", "int64": "long", "binary": "binary", "bool": "boolean"}
    return ", ".join(f"{f.name} {names[str(f.type)]}" for f in schema)


def _batch(schema: pa.Schema, rows: int, **cols) -> pa.RecordBatch:
    """A batch of ``rows`` rows; columns that aren't given are null."""
    return pa.RecordBatch.from_arrays([pa.array(cols[f.name], f.type) if f.name in cols else pa.nulls(rows, f.type) for f in schema], schema=schema)


def _docs_through(batch: pa.RecordBatch, at: pa.Array, schema: pa.Schema, **more) -> Iterator[pa.RecordBatch]:
    docs = batch.filter(at)
    if docs.num_rows:
        yield _batch(schema, docs.num_rows, **{n: docs.column(n) for n, _ in _DOC}, **{k: np.full(docs.num_rows, v) for k, v in more.items()})


def _signer(parts: int, scheme: Scheme):
    """Batches of (doc_id, tag, text) -> documents' facts, dealt evenly, and packed hashes."""

    def sign(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        held: dict[int, list] = {r: [] for r in range(4)}
        size, seen, turn = 0, set(), 0

        def out() -> pa.RecordBatch:
            nonlocal size
            rows = []
            for role, got in held.items():
                if got:
                    rows += [(role, *r) for r in _pack(parts, np.concatenate([c for c, _ in got]), np.concatenate([s for _, s in got]))]
                got.clear()
            size = 0
            role, part, classes, counts, hashes = zip(*rows)
            return _batch(_PACKED, len(rows), part=part, role=role, classes=classes, counts=counts, hashes=hashes)

        for batch in batches:
            for a in range(0, batch.num_rows, 500):
                some = batch.slice(a, 500)
                sets = [shingle_set(t.as_py()) for t in some.column("text")]
                n = np.fromiter(map(len, sets), np.int64, len(sets))
                digest = np.array([class_of(s) if len(s) else (0, 0) for s in sets], np.int64).reshape(-1, 2)
                cls, filled, spare = digest[:, 0], np.zeros(len(sets), np.int64), np.zeros(len(sets), np.int64)
                full = np.flatnonzero(n)
                if len(full):
                    ends = bands(int(n.max()))
                    m = scheme.segments(ends)
                    d = scheme.deletable(ends, m)
                    band = np.searchsorted(ends, n[full])
                    keys = [tuple(x) for x in digest[full].tolist()]
                    live = np.array([k not in seen for k in keys])  # copies within a task are signed once
                    seen.update(keys)
                    if len(seen) > 500_000:
                        seen = set(keys)
                    own = [sets[i] for i in full]
                    for up, roles in ((0, (OWN, OWN_DELETED)), (1, (BELOW, BELOW_DELETED))):
                        whole, thin, f, v = signatures(own, band + up, m, d)
                        if not up:
                            filled[full], spare[full] = f, v
                        for role, (row, sig) in zip(roles, (whole, thin)):
                            keep = live[row]
                            held[role].append((cls[full][row[keep]], sig[keep]))
                            size += int(keep.sum())
                at = (np.arange(turn, turn + len(sets)) * 7919 + len(seen)) % parts  # any partition will do
                turn += len(sets)
                yield _batch(_PACKED, len(sets), part=at, role=np.full(len(sets), -1), doc_id=some.column("doc_id"), tag=some.column("tag"), n=n, cls=cls, check=digest[:, 1], filled=filled, spare=spare)
                if size >= FLUSH:
                    yield out()
        if size:
            yield out()
        give_back()

    return sign


def _wide(low: bytes) -> np.ndarray:
    out = np.zeros((len(low) // 5, 8), np.uint8)
    out[:, :5] = np.frombuffer(low, np.uint8).reshape(-1, 5)
    return out.view("<i8").ravel()


def _cut(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
    """Pass documents on (as slice -1); cut packed hashes into slices by their highest eight bits."""
    cls, sig, role, size, part = [], [], [], 0, 0

    def out() -> pa.RecordBatch:
        nonlocal size
        c, s, r = np.concatenate(cls), np.concatenate(sig), np.concatenate(role)
        cls.clear(), sig.clear(), role.clear()
        size, k = 0, s >> 32
        order = np.argsort(k, kind="stable")
        c, s, r, k = c[order], s[order], r[order], k[order]
        edge = np.flatnonzero(np.r_[True, k[1:] != k[:-1]])
        ends = list(zip(edge, np.r_[edge[1:], len(k)]))
        return _batch(_SLICED, len(ends), slice=k[edge], part=np.full(len(ends), part), classes=[c[a:b].tobytes() for a, b in ends], roles=[r[a:b].tobytes() for a, b in ends], hashes=[s[a:b].tobytes() for a, b in ends])

    for batch in batches:
        is_doc = np.array([r < 0 for r in batch.column("role").to_pylist()], bool)
        yield from _docs_through(batch, pa.array(is_doc), _SLICED, slice=-1)
        for i in np.flatnonzero(~is_doc).tolist():
            counts = np.frombuffer(batch.column("counts")[i].as_py(), "<u2")
            cls.append(np.repeat(np.frombuffer(batch.column("classes")[i].as_py(), np.int64), counts))
            sig.append(_wide(batch.column("hashes")[i].as_py()))
            role.append(np.full(len(sig[-1]), batch.column("role")[i].as_py(), np.int8))
            size, part = size + len(sig[-1]), batch.column("part")[i].as_py()
            if size >= CUT:
                yield out()
    if size:
        yield out()
    give_back()


def _shared(part: int, cls: np.ndarray, sig: np.ndarray, role: np.ndarray) -> Iterator[pa.RecordBatch]:
    """Of the hashes of whole slices: those of a group with two classes, one of them in its own band, one with its whole segment."""
    order = np.argsort(sig, kind="stable")
    s = sig[order]
    twin = np.r_[False, s[1:] == s[:-1]]
    order = order[twin | np.r_[twin[1:], False]]  # most hashes stand alone
    del s, twin
    cls, sig, role = cls[order], sig[order], role[order]
    order = np.lexsort((role, cls, sig))
    cls, sig, role = cls[order], sig[order], role[order]
    keep = np.r_[True, (sig[1:] != sig[:-1]) | (cls[1:] != cls[:-1]) | (role[1:] != role[:-1])] if len(sig) else np.zeros(0, bool)
    cls, sig, role = cls[keep], sig[keep], role[keep]
    if not len(sig):
        return
    start = np.flatnonzero(np.r_[True, sig[1:] != sig[:-1]])
    group = np.repeat(np.arange(len(start)), np.diff(np.r_[start, len(sig)]))
    other = np.r_[True, (sig[1:] != sig[:-1]) | (cls[1:] != cls[:-1])]
    size = np.add.reduceat(other.astype(np.int64), start)
    own = np.add.reduceat((role < BELOW).astype(np.int64), start)
    entire = np.add.reduceat((role % 2 == 0).astype(np.int64), start)
    use = ((size > 1) & (own > 0) & (entire > 0))[group]
    cls, sig, role, size = cls[use], sig[use] | (part << 40), role[use], size[group][use]
    for a in range(0, len(cls), 50_000):
        b = slice(a, a + 50_000)
        yield _batch(_REPORT, len(cls[b]), cls=cls[b], sig=sig[b], role=role[b].astype(np.int32), size=size[b], report=np.ones(len(cls[b]), bool))


def _report(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
    """Pass documents on; of slices in order, what their groups share. Holds whole slices until there are SORTED hashes."""
    cls, sig, role, size, at, part = [], [], [], 0, -1, 0
    for batch in batches:
        k = np.array(batch.column("slice").to_pylist(), np.int64)
        yield from _docs_through(batch, pa.array(k < 0), _REPORT, report=False)
        for i in np.flatnonzero(k >= 0).tolist():
            if k[i] != at and size >= SORTED:
                yield from _shared(part, np.concatenate(cls), np.concatenate(sig), np.concatenate(role))
                cls, sig, role, size = [], [], [], 0
            at, part = int(k[i]), batch.column("part")[i].as_py()
            cls.append(np.frombuffer(batch.column("classes")[i].as_py(), np.int64))
            sig.append(np.frombuffer(batch.column("hashes")[i].as_py(), np.int64))
            role.append(np.frombuffer(batch.column("roles")[i].as_py(), np.int8))
            size += len(sig[-1])
    if size:
        yield from _shared(part, np.concatenate(cls), np.concatenate(sig), np.concatenate(role))
    give_back()


def _similar(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
    """Of pairs with their sets, those that are similar."""
    for batch in batches:
        keep, last, x = [], None, None
        for a, b in zip(batch.column("m_u"), batch.column("m_v")):
            if last is None or a != last:
                last, x = a, np.frombuffer(a.as_py(), np.uint64)
            y = np.frombuffer(b.as_py(), np.uint64)
            at = np.searchsorted(x, y)
            at[at == len(x)] = 0
            both = int((x[at] == y).sum())
            keep.append(100 * both >= 75 * (len(x) + len(y) - both))
        yield batch.select(["u", "v"]).filter(pa.array(keep, pa.bool_()))


def _bits(spots: DataFrame) -> bytes:
    """A filter of fixed size: bit p is set for each p of ``spots``."""
    bits = spots.groupBy(F.shiftright("p", 6).alias("w")).agg(F.bit_or(F.expr("shiftleft(1L, cast(p % 64 as int))")).alias("b"))
    got = bits.toArrow()  # at most 2^(BITS - 6) words of 8 bytes
    words = np.zeros(1 << (BITS - 6), np.int64)
    words[got.column("w").to_numpy()] = got.column("b").to_numpy()
    return words.tobytes()


def _sets_of(docs: DataFrame, wanted: DataFrame) -> DataFrame:
    """(cls, check, members binary) of the classes in ``wanted`` (cls, check, doc_id): one scan behind a filter of fixed size, then an exact join."""
    spot = F.shiftrightunsigned(F.xxhash64("doc_id"), 64 - BITS)
    filt = docs.sparkSession.sparkContext.broadcast(_bits(wanted.select(spot.alias("p"))))

    def scan(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        w = np.frombuffer(filt.value, np.uint64)
        for batch in batches:
            p = batch.column("p").to_numpy()
            hit = np.flatnonzero((w[p >> 6] >> (p & 63).astype(np.uint64)) & np.uint64(1))
            for a in range(0, len(hit), 500):
                sets = [shingle_set(batch.column("text")[i].as_py()) for i in hit[a : a + 500].tolist()]
                digest = np.array([class_of(s) for s in sets], np.int64).reshape(-1, 2)
                yield pa.RecordBatch.from_arrays([pa.array(digest[:, 0]), pa.array(digest[:, 1]), pa.array([s.tobytes() for s in sets], pa.binary())], names=["cls", "check", "members"])

    found = docs.where("text is not null").select("text", spot.alias("p")).mapInArrow(scan, "cls long, check long, members binary")
    found = found.join(wanted.select("cls", "check").distinct(), ["cls", "check"], "left_semi")
    return found.groupBy("cls", "check").agg(F.first("members").alias("members"))


def _verify(pairs: DataFrame, sets: DataFrame) -> DataFrame:
    """The (u, v) that are similar. A hot class's set goes to its pairs by a join that Spark can split."""
    a, b = (sets.select(F.col("cls").alias(c), F.col("members").alias(f"m_{c}")) for c in ("u", "v"))
    return pairs.join(a, "u").join(b, "v").select("u", "v", "m_u", "m_v").mapInArrow(_similar, "u long, v long")


def _fits(a: str, b: str):
    return F.expr(f"4 * least({a}, {b}) >= 3 * greatest({a}, {b})")


def _classes(rows: DataFrame) -> DataFrame:
    """id, cls, check, doc_id, n, filled, spare of each class. The id is the digest's first half; of several classes with one, all but the first get another."""
    kinds = rows.where("n > 0").groupBy("cls", "check").agg(F.min("doc_id").alias("doc_id"), F.first("n").alias("n"), F.first("filled").alias("filled"), F.first("spare").alias("spare"))
    turn = F.row_number().over(W.partitionBy("cls").orderBy("check"))  # nearly always one row
    return kinds.withColumn("id", F.when(turn == 1, F.col("cls")).otherwise(F.xxhash64("cls", "check")))


def jaccard_links(docs: DataFrame, tag: Column | None = None, rounds: int = 1, scheme: Scheme = Scheme()) -> tuple[DataFrame, DataFrame, DataFrame]:
    """(rows, classes, links): per document doc_id, tag, n, cls, check; per class its id; and verified links (u, v) between ids that join all that are similar.
    ``tag``: a long that travels with each row, to tell rows with one id apart."""
    spark = docs.sparkSession
    docs = docs.select(F.col("doc_id").cast("long").alias("doc_id"), (F.lit(0) if tag is None else tag).cast("long").alias("tag"), "text")
    parts = int(spark.conf.get("spark.sql.shuffle.partitions"))
    packed = docs.mapInArrow(_signer(parts, scheme), _ddl(_PACKED)).repartitionById(parts, F.col("part"))
    sliced = packed.mapInArrow(_cut, _ddl(_SLICED)).sortWithinPartitions("slice")
    found = hand_over(sliced.mapInArrow(_report, _ddl(_REPORT)), "signatures", "report", BATCH)
    rows, reports = part_of(found, "report", False).select(*[n for n, _ in _DOC]), part_of(found, "report", True)
    kinds = hand_over(_classes(rows), "classes")
    need = F.expr("2 * n div 7 + 1")
    shared = reports.select("cls", "sig", "role", "size").join(kinds, "cls").drop("cls", "check").withColumnRenamed("id", "cls")
    # Allocation: unshared segments are free; the rest comes from the smallest groups. Short sets use all they have.
    by_class = W.partitionBy("cls")
    shared = shared.withColumn("matched", F.sum((F.col("role") == OWN).cast("int")).over(by_class)).withColumn("need", need - F.col("filled") + F.col("matched"))
    shared = shared.withColumn("turn", F.row_number().over(W.partitionBy("cls", "role").orderBy("size", "sig")))
    short = F.col("filled") < need
    probes = F.when(short, F.col("role") < BELOW).otherwise((F.col("role") == OWN) & (F.col("turn") <= F.col("need")))
    shared = hand_over(shared.select("cls", "sig", "role", "n", "size", F.coalesce(probes, F.lit(False)).alias("probe")), "shared")
    release(reports)
    probed = shared.where("probe").select(F.col("sig").alias("asked")).distinct()
    live = hand_over(shared.join(probed, F.col("sig") == F.col("asked"), "left_semi").select("cls", "sig", "n", "probe"), "live")
    release(shared)
    links, steps = spark.createDataFrame([], "u long, v long"), []
    lost = kinds.where(F.expr("filled + spare < 2 * n div 7 + 1"))
    leftover = not lost.isEmpty()
    if live.isEmpty() and not leftover:
        return rows, kinds, links
    wanted = kinds.join(live.select(F.col("cls").alias("id")).distinct(), "id", "left_semi")
    if leftover:
        extra = hand_over(_prefix_pairs(docs, lost, kinds), "prefix-pairs", batch=BATCH)
        wanted = wanted.union(kinds.join(extra.select(F.explode(F.array("u", "v")).alias("id")).distinct(), "id", "left_semi")).distinct()
    sets = hand_over(_sets_of(docs, wanted.select("cls", "check", "doc_id")).join(kinds.select("id", "cls", "check"), ["cls", "check"]).select(F.col("id").alias("cls"), "members"), "sets", batch=BATCH)
    if leftover:
        steps.append(hand_over(_verify(extra, sets), "links", batch=BATCH))
        release(extra)
    # Leader rounds, then whatever pairs are still open. Labels only ever join what verified links join.
    labelled, former, tested = live.withColumn("label", F.col("cls")), live, None
    for turn in range(rounds + 1):
        # Groups that still hold two labels, one of them asking. Summed before the exchange, so that no group meets in one task.
        open_ = labelled.groupBy("sig").agg(F.min("label").alias("a"), F.max("label").alias("b"), F.max("probe").alias("p")).where("a != b and p").select(F.col("sig").alias("osig"))
        labelled = hand_over(labelled.join(open_, F.col("sig") == F.col("osig"), "left_semi"), "labelled")
        release(former)
        former = labelled
        if turn == rounds:
            size = labelled.groupBy("sig").agg(F.count("*").alias("k"), F.sum("n").alias("total")).where((F.col("k") > JOINED) | (F.col("total") > TOKENS))
            size = hand_over(size.select(F.col("sig").alias("hsig"), F.ceil(F.greatest(F.col("k") / BLOCK, F.col("total") / TOKENS)).cast("int").alias("blocks")), "hot-groups")
            if not size.isEmpty():
                steps.append(hand_over(_hot_links(labelled, size, sets), "links", batch=BATCH))
                labelled = labelled.join(size, F.col("sig") == F.col("hsig"), "left_anti")
            p = labelled.where("probe").select("sig", F.col("cls").alias("u"), F.col("n").alias("pn"), F.col("label").alias("pl"))
            q = labelled.select("sig", F.col("cls").alias("v"), F.col("n").alias("qn"), F.col("label").alias("ql"))
            pairs = p.join(q, "sig").where("pl != ql and qn <= pn and 4 * qn >= 3 * pn").select(F.greatest("u", "v").alias("u"), F.least("u", "v").alias("v")).distinct()
            pairs = hand_over(pairs.join(tested, ["u", "v"], "left_anti") if tested is not None else pairs, "pairs")
            release(former, size)
            steps.append(hand_over(_verify(pairs, sets), "links", batch=BATCH))
            release(pairs)
            break
        # Of each group the class that shares most leads; each class asks the leader it meets most often.
        weight = hand_over(labelled.withColumn("weight", F.count("*").over(W.partitionBy("cls"))), "weights")
        lead = weight.groupBy("sig").agg(F.max(F.struct("weight", "cls", "n", "label")).alias("l")).select(F.col("sig").alias("lsig"), "l")
        met = weight.join(lead, F.col("sig") == F.col("lsig")).where((F.col("label") != F.col("l.label")) & _fits("n", "l.n"))
        met = met.groupBy("cls", F.col("l.cls").alias("leader")).agg(F.count("*").alias("times"))
        asked = met.groupBy("cls").agg(F.max(F.struct("times", "leader")).alias("m")).select(F.col("cls").alias("u"), F.col("m.leader").alias("v"))
        asked = hand_over(asked, "asked")
        release(weight)
        if asked.isEmpty():
            continue
        both = asked.select(F.greatest("u", "v").alias("u"), F.least("u", "v").alias("v"))
        tested = both if tested is None else tested.union(both)
        found_links = hand_over(_verify(asked, sets), "links", batch=BATCH)
        steps.append(found_links)
        # A class takes its leader's label; leaders outweigh their followers, so this can't go round in circles.
        up = found_links.select(F.col("u").alias("node"), F.col("v").alias("root"))
        twice = up.join(up.select(F.col("node").alias("mid"), F.col("root").alias("top")), F.col("root") == F.col("mid"), "left").select("node", F.coalesce("top", "root").alias("root"))
        labelled = labelled.join(twice, F.col("cls") == F.col("node"), "left")
        labelled = labelled.withColumn("label", F.coalesce("root", "label")).drop("node", "root")
    release(sets)
    for found_links in steps:
        links = links.union(found_links)
    return rows, kinds, links


def _hot_links(labelled: DataFrame, hot: DataFrame, sets: DataFrame) -> DataFrame:
    """Links within large groups. A group is dealt into blocks, each pair of blocks is one task's unit, and a unit counts all its overlaps by matrix
    products; it returns links that join whatever its similar pairs join (at most one per member), so no pairs travel."""

    out = pa.schema([("u", pa.int64()), ("v", pa.int64())])

    def unit(group: pa.Table) -> pa.Table:
        group = group.take(pa.array(np.unique(group.column("cls").to_numpy(), return_index=True)[1]))
        labels = group.column("label").to_pylist()
        if len(set(labels)) < 2:
            return out.empty_table()
        n, cls, probe, side = (group.column(c).to_numpy() for c in ("n", "cls", "probe", "side"))
        members = [np.frombuffer(m.as_py(), np.uint64) for m in group.column("members")]
        row = np.repeat(np.arange(len(members)), [len(m) for m in members])
        _, token, count = np.unique(np.concatenate(members), return_inverse=True, return_counts=True)
        common = count > 1
        place = np.cumsum(common) - 1
        keep = common[token]
        row, token = row[keep], place[token[keep]]
        order = np.argsort(token, kind="stable")
        row, token = row[order], token[order]
        both = np.zeros((len(n), len(n)), np.float32)
        for a in range(0, int(common.sum()), 4096):
            lo, hi = np.searchsorted(token, [a, a + 4096])
            x = np.zeros((len(n), 4096), np.float32)
            x[row[lo:hi], token[lo:hi] - a] = 1
            both += x @ x.T
        near = 100 * both >= 75 * (n[:, None] + n[None, :] - both)
        near &= (probe[:, None] | probe[None, :]) & ((side[:, None] != side[None, :]) | (side.min() == side.max()))
        root = {}

        def top(c):
            while (p := root.get(c, c)) != c:
                root[c] = c = root.get(p, p)
            return c

        cls = cls.tolist()  # plain ints: they are compared with the tuples of labels
        for c, lab in zip(cls, labels):
            root[top(c)] = top(("label", lab))
        found = []
        for i, j in zip(*np.nonzero(np.triu(near, 1))):
            a, b = top(cls[i]), top(cls[j])
            if a != b:
                root[a] = b
                found.append((max(cls[i], cls[j]), min(cls[i], cls[j])))
        return pa.table([pa.array([f[k] for f in found], pa.int64()) for k in (0, 1)], schema=out)

    rows = labelled.join(hot, F.col("sig") == F.col("hsig")).groupBy("sig", "cls").agg(F.max("probe").alias("probe"), F.first("n").alias("n"), F.first("label").alias("label"), F.first("blocks").alias("blocks"))
    rows = rows.withColumn("own", F.pmod(F.xxhash64("cls", F.lit(7)), F.col("blocks")).cast("int"))
    rows = rows.withColumn("other", F.explode(F.sequence(F.lit(0), F.col("blocks") - 1))).withColumns({"lo": F.least("own", "other"), "hi": F.greatest("own", "other"), "side": F.col("own") > F.col("other")})
    return rows.join(sets, "cls").select("sig", "lo", "hi", "cls", "probe", "n", "label", "side", "members").groupBy("sig", "lo", "hi").applyInArrow(unit, "u long, v long").distinct()


def _prefix_pairs(docs: DataFrame, lost: DataFrame, kinds: DataFrame) -> DataFrame:
    """Candidates (u, v) of sets that segments can't cover: any partner holds one of the n div 4 + 1 least shingles of the larger set, and is in its band or the one below."""
    asked = _sets_of(docs, lost.select("cls", "check", "doc_id")).join(lost.select("id", "cls", "check", "n"), ["cls", "check"])

    def prefix(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in batches:
            for i, m, n in zip(batch.column("id").to_pylist(), batch.column("members").to_pylist(), batch.column("n").to_pylist()):
                s = np.frombuffer(m, np.int64)[: n // 4 + 1]
                ends = bands(n)
                yield pa.RecordBatch.from_arrays([pa.array(np.full(len(s), i)), pa.array(np.full(len(s), n)), pa.array(s), pa.array(_spot(s.view(np.uint64), np.searchsorted(ends, n)))], names=["u", "pn", "token", "p"])

    asked = hand_over(asked.select("id", "members", "n").mapInArrow(prefix, "u long, pn long, token long, p long"), "asked-tokens", batch=BATCH)
    filt = docs.sparkSession.sparkContext.broadcast(_bits(asked.select("p")))

    def spread(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        w = np.frombuffer(filt.value, np.uint64)
        for batch in batches:
            for t in batch.column("text"):
                s = shingle_set(t.as_py())
                if len(s):
                    band = np.searchsorted(bands(len(s)), len(s))
                    hit = np.zeros(len(s), bool)
                    for up in (0, 1):
                        p = _spot(s, band + up)
                        hit |= ((w[p >> 6] >> (p & 63).astype(np.uint64)) & np.uint64(1)).astype(bool)
                    if hit.any():
                        c, k = class_of(s)
                        got = s[hit].view(np.int64)
                        yield pa.RecordBatch.from_arrays([pa.array(np.full(len(got), x)) for x in (c, k, len(s))] + [pa.array(got)], names=["cls", "check", "qn", "token"])

    met = docs.where("text is not null").select("text").mapInArrow(spread, "cls long, check long, qn long, token long").distinct().join(asked.drop("p"), "token")
    met = met.where("qn <= pn and 4 * qn >= 3 * pn").select("u", "cls", "check").distinct().join(kinds.select("id", "cls", "check"), ["cls", "check"])
    return met.where("u != id").select("u", F.col("id").alias("v")).distinct()


def _spot(tokens: np.ndarray, band: int) -> np.ndarray:
    """The place of shingles of a set in one band in a filter of 2^BITS bits."""
    with np.errstate(over="ignore"):
        return (_mix(tokens + np.uint64(band) * _K[2]) >> np.uint64(64 - BITS)).astype(np.int64)


def jaccard_components(docs: DataFrame, tag: Column | None = None, scheme: Scheme = Scheme()) -> DataFrame:
    """One row per document: doc_id, n_shingles, component_id (the smallest id that links reach), tag and group (a name of the component; null without shingles)."""
    rows, kinds, links = jaccard_links(docs, tag, scheme=scheme)
    roots = components(links)
    named = kinds.join(roots, F.col("id") == F.col("node"), "left").select("cls", "check", F.col("doc_id").alias("least"), F.coalesce("root", "id").alias("root"))
    least = named.groupBy("root").agg(F.min("least").alias("component_id"))
    named = named.join(least, "root").select("cls", "check", "component_id", F.col("root").alias("group"))
    full = rows.where("n > 0").join(named, ["cls", "check"]).select("doc_id", F.col("n").alias("n_shingles"), "component_id", "tag", "group")
    return full.unionByName(rows.where("n = 0").select("doc_id", F.col("n").alias("n_shingles"), F.col("doc_id").alias("component_id"), "tag", F.lit(None).cast("long").alias("group")))


def query(spark: SparkSession, sf_dir: str) -> DataFrame:
    return jaccard_components(table(spark, sf_dir, "documents").select("doc_id", "text")).select("doc_id", "n_shingles", "component_id")


ORACLE_SQL = r"""
WITH RECURSIVE w AS (SELECT doc_id, regexp_extract_all(translate(text, 'ABCDEFGHIJKLMNOPQRSTUVWXYZ', 'abcdefghijklmnopqrstuvwxyz'), '[^\x20\x09-\x0D]+') AS w FROM documents),
s AS (SELECT doc_id, list_distinct(CASE WHEN len(w) = 0 OR w IS NULL THEN [] WHEN len(w) < 5 THEN [array_to_string(w, ' ')]
        ELSE list_transform(generate_series(1, len(w) - 4), lambda i: array_to_string(w[i:i + 4], ' ')) END) AS s FROM w),
t AS (SELECT doc_id, len(s) AS n, unnest(s) AS g FROM s),
o AS (SELECT a.doc_id AS x, b.doc_id AS y, count(*) AS k, any_value(a.n) AS nx, any_value(b.n) AS ny FROM t a JOIN t b ON a.g = b.g AND a.doc_id < b.doc_id GROUP BY 1, 2),
e AS (SELECT x, y FROM o WHERE 100 * k >= 75 * (nx + ny - k)),
b AS (SELECT x, y FROM e UNION SELECT y, x FROM e),
r(doc_id, root) AS (SELECT doc_id, doc_id FROM s UNION SELECT b.y, r.root FROM r JOIN b ON r.doc_id = b.x)
SELECT s.doc_id, len(s.s)::BIGINT AS n_shingles, min(r.root)::BIGINT AS component_id FROM s JOIN r ON r.doc_id = s.doc_id GROUP BY s.doc_id, s.s
"""
