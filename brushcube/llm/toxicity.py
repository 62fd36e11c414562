"""Toxicity by compression distance: two zstandard dictionaries, window lengths, calibrated thresholds.

Both dictionaries hold the same common words of ordinary text; one ends in words that mark toxic text, the other in as many more ordinary
words. A text is cut into windows of WINDOW words; a window that the toxic dictionary shortens by at least
COARSE bytes more than the other is cut again into single words (each between fixed common words, so that
short inputs compress at all) and measured again. A logistic model on the largest coarse and fine gains
and the number of fine gains gives the score; it is calibrated on documents that the dictionaries of its fold have not seen.

Learning reads only labelled rows whose crc32(doc_id) mod 5 is not 0: of the TRAIN_TOXIC and TRAIN_ORDINARY lowest by
hash those with texts of at most TRAIN_CHARS characters, which are read whole; near copies count once. Scoring reads
every whole text, and nothing but the text.

Defined results: null, empty and wordless texts get the model's score of no gain; without labels of both classes every score is 0;
repeated rows score alike; a null id is neither held out nor learnt from (held_out is null); a document with several labels counts as toxic if any says so; columns of the input are kept.
"""

from __future__ import annotations

import math
import re
from collections import Counter
from collections.abc import Iterator
from dataclasses import dataclass, field

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from .common import give_back, table

TRAIN_TOXIC, TRAIN_ORDINARY, TRAIN_CHARS = 1500, 4500, 65_536
COMMON, MARKS, WINDOW, COARSE, FINE, STEMS = 12_000, 1_000, 6, 2, 2, (4, 5, 6)
_WORD = re.compile(r"[^\x00-\x2F\x3A-\x60\x7B-\x7F]+")


def words(text: str | None) -> list[str]:
    return _WORD.findall(text.lower()) if text else []


def _compressor(content: list[str]):
    import zstandard

    d = zstandard.ZstdCompressionDict((" " + " ".join(content) + " ").encode(), dict_type=zstandard.DICT_TYPE_RAWCONTENT)
    p = zstandard.ZstdCompressionParameters.from_level(3, write_content_size=False, write_checksum=False, write_dict_id=False)
    d.precompute_compress(compression_params=p)
    return zstandard.ZstdCompressor(dict_data=d, compression_params=p)


@dataclass
class ToxicityModel:
    """Words of the dictionaries, and the logistic model. Its size is bounded by COMMON and MARKS."""

    common: list[str] = field(default_factory=list)
    marks: list[str] = field(default_factory=list)
    weights: list[float] = field(default_factory=list)

    def open(self) -> None:
        self.toxic = _compressor(self.common + self.marks)
        self.plain = _compressor(self.common + self.common[-len(self.marks):])
        self.pad = (" " + " ".join(self.common[-40:-20]) + " ").encode()

    def gains(self, windows: list[bytes]) -> np.ndarray:
        """Bytes that the toxic dictionary saves more than the plain one."""
        sizes = [np.fromiter((len(x) for x in c.multi_compress_to_buffer(windows)), np.int64, len(windows)) for c in (self.plain, self.toxic)]
        return sizes[0] - sizes[1]

    def features(self, text: str | None) -> tuple[float, float, float]:
        coarse, suspects, ws = 0, set(), words(text)
        for block in range(0, len(ws), WINDOW * 20_000):
            part = ws[block : block + WINDOW * 20_000]
            gain = self.gains([(" " + " ".join(part[i : i + WINDOW]) + " ").encode() for i in range(0, len(part), WINDOW)])
            coarse = max(coarse, int(gain.max()))
            suspects.update(w for i in np.nonzero(gain >= COARSE)[0] for w in part[i * WINDOW : (i + 1) * WINDOW])
        fine = self.gains([self.pad + f"{w} {w[::-1]} ".encode() for w in sorted(suspects)]) if suspects else np.zeros(1)
        return min(coarse, 12.0), float(np.clip(fine.max(), 0, 12)), math.log1p(int((fine >= FINE).sum()))

    def score(self, text: str | None) -> float:
        if not self.weights:
            return 0.0
        z = self.weights[0] + sum(w * x for w, x in zip(self.weights[1:], self.features(text), strict=True))
        return 1 / (1 + math.exp(-max(-30.0, min(30.0, z))))


def _fresh(texts: list[str]) -> list[str]:
    """The texts without near copies of earlier ones."""
    seen: set[int] = set()
    kept = []
    for t in texts:
        w = words(t)
        grams = {hash(tuple(w[i : i + 3])) for i in range(max(1, len(w) - 2))}
        if len(grams & seen) <= 0.2 * len(grams):
            kept.append(t)
            seen |= grams
    return kept


def _dictionaries(toxic: list[str], ordinary: list[str]) -> ToxicityModel:
    # marks may be whole words or beginnings of words (stems of inflected ones)
    ct, co = (Counter(w for t in ts for w in {p for w in words(t) for p in (w, *(w[:k] for k in STEMS if k < len(w)))}) for ts in (toxic, ordinary))
    known = Counter(w for t in ordinary for w in set(words(t)))
    nt, no = len(toxic), len(ordinary)

    def evidence(w: str) -> float:
        a, b = ct[w], co[w]
        p = (a + b) / (nt + no)
        return 2 * (a * math.log(a / (nt * p)) + (b * math.log(b / (no * p)) if b else 0))

    marks = [w for w in ct if ct[w] >= 3 and (ct[w] + 0.5) / nt > 5 * (co[w] + 0.5) / no and evidence(w) > 20]
    marks = sorted(marks, key=lambda w: (evidence(w), w))[-MARKS:]
    taken = set(marks)
    common = sorted((w for w in known if w not in taken), key=lambda w: (-known[w], w))[:COMMON][::-1]
    return ToxicityModel(common, marks)


def _logistic(x: np.ndarray, y: np.ndarray, weight: np.ndarray) -> list[float]:
    x = np.hstack([np.ones((len(x), 1)), x])
    b = np.zeros(x.shape[1])
    ridge = np.diag([1e-6] + [1e-2] * (x.shape[1] - 1))
    for _ in range(50):
        p = 1 / (1 + np.exp(-np.clip(x @ b, -30, 30)))
        step = np.linalg.solve((x.T * (weight * p * (1 - p))) @ x + ridge, x.T @ (weight * (y - p)) - ridge @ b)
        b = b + step
        if np.abs(step).max() < 1e-8:
            break
    return [float(v) for v in b]


def train(toxic: list[str], ordinary: list[str], toxic_share: float | None = None) -> ToxicityModel:
    """A model from two lists of texts; ``toxic_share``: of the labelled population, if the lists are dealt otherwise."""
    toxic, ordinary = _fresh(toxic), _fresh(ordinary)
    if len(toxic) < 2 or len(ordinary) < 2:
        return ToxicityModel()
    rows, y = [], []
    for fold in (0, 1):
        m = _dictionaries(toxic[fold::2], ordinary[fold::2])
        if not m.marks:
            continue
        m.open()
        for label, held in ((1, toxic[1 - fold :: 2]), (0, ordinary[1 - fold :: 2])):
            rows += [m.features(t) for t in held]
            y += [label] * len(held)
    model = _dictionaries(toxic, ordinary)
    if not rows or not model.marks:
        return ToxicityModel()
    y = np.array(y, dtype=float)
    share = toxic_share or y.mean()
    model.weights = _logistic(np.array(rows), y, np.where(y == 1, share / y.mean(), (1 - share) / (1 - y.mean())))
    return model


def in_training(doc_id: str = "doc_id"):
    return F.crc32(F.col(doc_id).cast("string").cast("binary")) % 5 != 0


def train_on(docs: DataFrame, labels: DataFrame, text: str = "text") -> ToxicityModel:
    """Learn from labelled documents outside the held-out fifth. What reaches the driver is bounded by the TRAIN_ parameters."""
    known = labels.where(F.col("doc_id").isNotNull() & F.col("toxic").isNotNull() & in_training()).groupBy("doc_id").agg(F.max("toxic").alias("toxic"))
    counts = {r["toxic"]: r["n"] for r in known.groupBy("toxic").agg(F.count("*").alias("n")).collect()}
    if not counts.get(1) or not counts.get(0):
        return ToxicityModel()
    pick = [known.where(F.col("toxic") == v).orderBy(F.xxhash64("doc_id"), "doc_id").limit(n) for v, n in ((1, TRAIN_TOXIC), (0, TRAIN_ORDINARY))]
    chosen = F.broadcast(pick[0].unionByName(pick[1]))  # at most TRAIN_TOXIC + TRAIN_ORDINARY rows of two numbers
    found = docs.join(chosen, "doc_id").select("toxic", F.coalesce(text, F.lit("")).alias("t"), F.xxhash64("doc_id").alias("h")).where(F.char_length("t") <= TRAIN_CHARS)
    # repeated ids could bring more rows than were chosen
    rows = found.orderBy("h", "t").limit(2 * (TRAIN_TOXIC + TRAIN_ORDINARY)).collect()
    return train([r["t"] for r in rows if r["toxic"] == 1], [r["t"] for r in rows if r["toxic"] == 0], counts[1] / (counts[0] + counts[1]))


def scorer(model: ToxicityModel):
    """An Arrow UDF text -> score."""
    facts = (model.common, model.marks, model.weights)

    @F.arrow_udf("double")
    def score(batches: Iterator[pa.Array]) -> Iterator[pa.Array]:
        m = ToxicityModel(*facts)
        if m.weights:
            m.open()
        for texts in batches:
            yield pa.array([m.score(t.as_py()) for t in texts], pa.float64())
        give_back()

    return score


def classify(docs: DataFrame, model: ToxicityModel, text: str = "text") -> DataFrame:
    """``docs`` with score and predicted."""
    out = docs.withColumn("score", scorer(model)(F.col(text)))
    return out.withColumn("predicted", (F.col("score") >= 0.5).cast("int"))


def query(spark: SparkSession, sf_dir: str) -> DataFrame:
    docs = table(spark, sf_dir, "documents").select("doc_id", "text")
    model = train_on(docs, table(spark, sf_dir, "labels").select("doc_id", "toxic"))
    return classify(docs, model).select("doc_id", (~in_training()).alias("held_out"), "score", "predicted")


ORACLE_SQL = None  # tests measure held-out accuracy
