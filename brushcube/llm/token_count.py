"""Token counts by rank-synchronous array merging, for a sentencepiece BPE model with byte fallback.

Texts are cut into pre-tokens that no piece crosses (before a run of spaces, and at characters that occur in no longer
piece). Distinct pre-tokens of a batch are held as symbol matrices, one per length. From the longest length down, every sequence's lowest-rank pair is found in
one vector step and applied to all sequences at once (the leftmost on ties), which makes each shorter by one: it joins the
matrix of the next length. A sequence without a mergeable pair is done, and its surviving symbols are counted: a piece as one, a
character outside the vocabulary as its UTF-8 bytes.

Sequences longer than LONG symbols (texts without spaces) are merged with a heap instead, n log n each, by the same order.

Defined results: a null or empty text has no tokens; nothing is trimmed, truncated or padded; control strings in a text are ordinary text, as the library has it;
repeated rows are counted alike; other columns are kept by ``count_tokens``.
"""

from __future__ import annotations

import heapq
import re
from collections.abc import Iterator
from functools import lru_cache

import numpy as np
import pandas as pd
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F
from pyspark.sql.types import LongType

from .common import table

LIMIT, LONG, CACHE, FAR = 4096, 192, 400_000, np.int32(2**31 - 1)
SPACE = "▁"


class RaggedMerger:
    """The merge tables of one model, and the counts of pre-tokens."""

    def __init__(self, model_file: str):
        import sentencepiece

        sp = sentencepiece.SentencePieceProcessor(model_file=model_file)
        usable = [i for i in range(sp.get_piece_size()) if not (sp.is_control(i) or sp.is_unknown(i) or sp.is_byte(i) or sp.is_unused(i))]
        pieces = {sp.id_to_piece(i): i for i in usable}
        scores = {i: sp.get_score(i) for i in usable}
        if any(SPACE in p.lstrip(SPACE) for p in pieces):
            raise ValueError("pieces of this model cross word starts")
        self.ids = {p: k for k, p in enumerate(pieces)}
        order = sorted(pieces, key=lambda p: -scores[pieces[p]])
        ranks = {p: r for r, p in enumerate(order)}
        for p in pieces:  # characters that only occur inside pieces
            for ch in p:
                self.ids.setdefault(ch, len(self.ids))
        self.weight = np.array([1 if p in pieces else len(p.encode()) for p in self.ids] + [1, 2, 3, 4], dtype=np.int64)
        self.unknown = len(self.ids) - 1  # + number of bytes
        self.base = np.int64(len(self.ids) + 8)
        merges = {}
        for p, r in ranks.items():
            for k in range(1, len(p)):
                left, right = self.ids.get(p[:k]), self.ids.get(p[k:])
                if left is not None and right is not None:
                    merges[left * int(self.base) + right] = (r, self.ids[p])
        keys = np.array(sorted(merges), dtype=np.int64)
        self.keys = np.append(keys, np.int64(2**62))
        self.ranks = np.array([merges[int(k)][0] for k in keys] + [FAR], dtype=np.int32)
        self.merged = np.array([merges[int(k)][1] for k in keys] + [0], dtype=np.int32)
        self.pairs = merges
        inner = {ch for p in pieces if len(p) > 1 for ch in p} - {SPACE}
        self.cut = re.compile(f"{SPACE}*[{''.join(re.escape(c) for c in sorted(inner))}]+|{SPACE}+|[^{SPACE}]", re.S)
        self.known: dict[str, int] = {}

    def symbols(self, word: str) -> list[int]:
        get, unknown = self.ids.get, self.unknown
        return [s if (s := get(c)) is not None else unknown + len(c.encode()) for c in word]

    def look_up(self, left: np.ndarray, right: np.ndarray) -> tuple[np.ndarray, np.ndarray]:
        key = left.astype(np.int64) * self.base + right
        at = np.searchsorted(self.keys, key)
        hit = self.keys[at] == key
        return np.where(hit, self.ranks[at], FAR), np.where(hit, self.merged[at], 0).astype(np.int32)

    def count(self, words: list[str]) -> list[int]:
        """Tokens of each pre-token."""
        out = np.zeros(len(words), dtype=np.int64)
        by_size: dict[int, tuple[list[int], list[list[int]]]] = {}
        for i, w in enumerate(words):
            if len(w) > LONG:
                out[i] = self.count_long(self.symbols(w))
            else:
                rows, syms = by_size.setdefault(len(w), ([], []))
                rows.append(i)
                syms.append(self.symbols(w))
        rows, sym, rank, into = np.empty(0, np.int64), None, None, None
        for size in range(max(by_size, default=0), 0, -1):
            if size in by_size:
                more = np.array(by_size[size][1], dtype=np.int32)
                more_rows = np.array(by_size[size][0], dtype=np.int64)
                more_rank, more_into = self.look_up(more[:, :-1], more[:, 1:])
                if len(rows):
                    rows, sym, rank, into = (np.concatenate(x) for x in ((rows, more_rows), (sym, more), (rank, more_rank), (into, more_into)))
                else:
                    rows, sym, rank, into = more_rows, more, more_rank, more_into
            if not len(rows):
                continue
            if size == 1:
                out[rows] = self.weight[sym].sum(axis=1)
                break
            at = rank.argmin(axis=1)
            line = np.arange(len(rows))
            live = rank[line, at] != FAR
            if not live.all():
                out[rows[~live]] = self.weight[sym[~live]].sum(axis=1)
                rows, sym, rank, into, at = rows[live], sym[live], rank[live], into[live], at[live]
                line = np.arange(len(rows))
            if not len(rows):
                continue
            sym[line, at] = into[line, at]
            drop = np.ones(sym.shape, dtype=bool)
            drop[line, at + 1] = False
            sym = sym[drop].reshape(len(rows), size - 1)
            rank, into = (x[drop[:, 1:]].reshape(len(rows), size - 2) for x in (rank, into))
            if size > 2:
                for there, lo in ((at > 0, at - 1), (at < size - 2, at)):
                    r, c = line[there], lo[there]
                    rank[r, c], into[r, c] = self.look_up(sym[r, c], sym[r, c + 1])
        return out.tolist()

    def count_long(self, sym: list[int]) -> int:
        n, base, pairs = len(sym), int(self.base), self.pairs
        after, before, heap = list(range(1, n + 1)), list(range(-1, n - 1)), []

        def offer(i: int, j: int) -> None:
            if i >= 0 and j < n and (m := pairs.get(sym[i] * base + sym[j])):
                heapq.heappush(heap, (m[0], i, j, sym[i], sym[j], m[1]))

        for i in range(n - 1):
            offer(i, i + 1)
        while heap:
            _, i, j, a, b, into = heapq.heappop(heap)
            if sym[i] != a or sym[j] != b or after[i] != j:
                continue
            sym[i], sym[j] = into, -1
            after[i] = after[j]
            if after[j] < n:
                before[after[j]] = i
            offer(before[i], i)
            offer(i, after[i])
        return sum(int(self.weight[s]) for s in sym if s >= 0)

    def count_texts(self, texts: list[str | None]) -> list[int]:
        cut, known = self.cut.findall, self.known
        parts = [cut(SPACE + t.replace(" ", SPACE)) if t else () for t in texts]
        fresh = {w for p in parts for w in p if w not in known}
        if len(known) + len(fresh) > CACHE:  # forget all but this batch: memory stays bounded
            known.clear()
            fresh = {w for p in parts for w in p}
        new = list(fresh)
        known.update(zip(new, self.count(new), strict=True))
        return [sum(map(known.__getitem__, p)) for p in parts]


@lru_cache(2)
def merger(model_file: str) -> RaggedMerger:
    return RaggedMerger(model_file)


def _batches(texts: list, most: int = 2_000_000) -> Iterator[list]:
    """Neighbouring texts of at most so many characters together (or one longer text)."""
    batch, size = [], 0
    for t in texts:
        n = len(t) if t else 0
        if batch and size + n > most:
            yield batch
            batch, size = [], 0
        batch.append(t)
        size += n
    if batch:
        yield batch


def token_counter(model: str):
    """A pandas UDF text -> tokens. ``model``: a file name for public_tokenizers.path, or a path."""

    @F.pandas_udf(LongType())
    def tokens(batches: Iterator[pd.Series]) -> Iterator[pd.Series]:
        import os

        if os.path.exists(model):
            path = model
        else:
            import public_tokenizers

            path = public_tokenizers.path(model)
        m = merger(str(path))
        for s in batches:
            counts = [n for batch in _batches(s.tolist()) for n in m.count_texts(batch)]
            yield pd.Series(counts, index=s.index, dtype="int64")

    return tokens


def count_tokens(docs: DataFrame, text: str = "text", model: str = "piece_bpe_32k.model", limit: int = LIMIT) -> DataFrame:
    """``docs`` with n_bytes, n_tokens and over_limit."""
    out = docs.withColumns({"n_bytes": F.coalesce(F.octet_length(text), F.lit(0)).cast("long"), "n_tokens": token_counter(model)(F.col(text))})
    return out.withColumn("over_limit", F.col("n_tokens") > limit)


def query(spark: SparkSession, sf_dir: str) -> DataFrame:
    docs = table(spark, sf_dir, "documents").select("doc_id", "text")
    return count_tokens(docs).select("doc_id", "n_bytes", "n_tokens", "over_limit")


ORACLE_SQL = None  # tests hold every count against the library's own
