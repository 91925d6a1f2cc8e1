"""Benchmark decontamination: every passage of every document queries a BM25 inverted index of the test items.

Impacts are divided by the item's score for its own text, so 1 means that the whole item was asked for and one
threshold serves all items.  Retrieval is block-max WAND with the pivot test taken for all blocks at once: postings
are kept twice, per block of items as the block's largest impact and per item; a query first sums block maxima, only
blocks whose sum reaches the threshold are scored, so every item above the threshold is found and no other block is
touched.  A document as a whole is the first query (a bound for its passages); its passages, overlapping windows at
least twice as long as the longest item, follow only if some item can pass.

Hits are verified in the window: the question part (the item but for its last quarter) and the answer part (that
quarter, five words at least) must each have ``overlap`` of their shingles there.  Shingles have five words; in parts of
under 14 words fewer, so that one changed word anywhere leaves at least half of a part's shingles.

Items are indexed in shards of at most ``shard_items`` items; only one shard at a time is collected and broadcast.
Defined results: null or empty text and null or empty items give no hits; repeated rows give repeated hits; ties don't
matter since all items above the threshold are returned; empty tables give an empty table.
"""

from __future__ import annotations

import math
import re
from collections import Counter
from collections.abc import Iterator
from functools import reduce

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

_WORD = re.compile(r"\w+")
K1, B, BLOCK, SHINGLE = 1.2, 0.75, 8, 5
DENSE = 4_000_000


def words_of(text: str | None) -> list[str]:
    return _WORD.findall((text or "").lower())


def shingles(words: list[str], size: int = SHINGLE) -> set[tuple[str, ...]]:
    if not words:
        return set()
    return {tuple(words[i : i + size]) for i in range(max(1, len(words) - size + 1))}


def part_size(n_words: int) -> int:
    """Words a shingle of a part has: the most, up to SHINGLE, for which one changed word spares half the shingles."""
    return max(1, min(SHINGLE, (n_words + 1) // 3))


class ItemIndex:
    """BM25 index of test items with block maxima; items are sorted by length so that blocks hold like items."""

    def __init__(self, items: list[tuple[int, str]]):
        kept = sorted(((i, w) for i, t in items if (w := words_of(t))), key=lambda x: (len(x[1]), x[0]))
        self.ids = [i for i, _ in kept]
        self.words = [w for _, w in kept]
        self.longest = max(map(len, self.words), default=0)
        n = len(kept)
        df = Counter(t for w in self.words for t in set(w))
        mean = sum(map(len, self.words)) / max(1, n)
        self.terms = {t: k for k, t in enumerate(sorted(df))}
        idf = {t: math.log(1 + (n - c + 0.5) / (c + 0.5)) for t, c in df.items()}
        triples = []
        for at, w in enumerate(self.words):
            norm = K1 * (1 - B + B * len(w) / mean)
            impact = {t: idf[t] * c * (K1 + 1) / (c + norm) for t, c in Counter(w).items()}
            own = sum(impact.values())
            triples += [(self.terms[t], at, v / own) for t, v in impact.items()]
        triples.sort()
        self.item = np.array([x[1] for x in triples], np.int64)
        self.impact = np.array([x[2] for x in triples])
        term = np.array([x[0] for x in triples], np.int64)
        bounds = np.arange(len(self.terms) + 1)
        self.item_at = np.searchsorted(term, bounds).tolist()
        block = self.item // BLOCK
        first = np.flatnonzero(np.r_[True, (term[1:] != term[:-1]) | (block[1:] != block[:-1])]) if len(term) else np.array([], np.int64)
        self.block = block[first]
        self.block_max = np.maximum.reduceat(self.impact, first) if len(first) else np.array([])
        self.block_at = np.searchsorted(term[first], bounds).tolist()
        self.n_blocks = (n + BLOCK - 1) // BLOCK
        self.table = None
        if 0 < len(self.terms) * n <= DENSE:  # same sums, as rows of two small matrices
            self.table = np.zeros((len(self.terms), self.n_blocks * BLOCK))
            self.table[term, self.item] = self.impact
            self.block_table = self.table.reshape(len(self.terms), self.n_blocks, BLOCK).max(axis=2)
        self.parts = {}
        for at, w in enumerate(self.words):
            tail = min(len(w), max(SHINGLE, len(w) // 4))
            halves = (w[: len(w) - tail] if len(w) - tail >= SHINGLE else w, w[len(w) - tail :])
            self.parts[at] = tuple((part_size(len(h)), shingles(h, part_size(len(h)))) for h in halves)

    def search(self, terms: list[int], threshold: float) -> list[tuple[int, float]]:
        """(item, score) of every item that the distinct query terms score at ``threshold`` or more."""
        if not terms:
            return []
        if self.table is not None:
            alive = np.flatnonzero(self.block_table[terms].sum(axis=0) >= threshold - 1e-9)
            found = []
            for k in alive.tolist():
                scores = self.table[terms, k * BLOCK : (k + 1) * BLOCK].sum(axis=0)
                found += [(k * BLOCK + int(i), float(scores[i])) for i in np.flatnonzero(scores >= threshold - 1e-9)]
            return found
        spans = [slice(self.block_at[t], self.block_at[t + 1]) for t in terms]
        bound = np.bincount(np.concatenate([self.block[s] for s in spans]), np.concatenate([self.block_max[s] for s in spans]), self.n_blocks)
        alive = bound >= threshold - 1e-9
        if not alive.any():
            return []
        spans = [slice(self.item_at[t], self.item_at[t + 1]) for t in terms]
        item, impact = np.concatenate([self.item[s] for s in spans]), np.concatenate([self.impact[s] for s in spans])
        asked = alive[item // BLOCK]
        scores = np.bincount(item[asked], impact[asked], len(self.ids))
        return [(int(i), float(scores[i])) for i in np.flatnonzero(scores >= threshold - 1e-9)]

    def hits(self, text: str | None, threshold: float, overlap: float) -> list[tuple[int, float, float, float]]:
        """(item id, score, question overlap, answer overlap) of the verified items, each once with its best score."""
        words = words_of(text)
        known = self.terms
        if not self.search([known[w] for w in known.keys() & set(words)], threshold):
            return []
        size = max(128, 2 * self.longest)
        best: dict[int, tuple[float, float, float]] = {}
        for a in range(0, max(1, len(words) - size // 2), size // 2):
            part = words[a : a + size]
            found = self.search([known[w] for w in known.keys() & set(part)], threshold)
            if not found:
                continue
            there: dict[int, set[tuple[str, ...]]] = {}
            for at, score in found:
                for k, _ in self.parts[at]:
                    if k not in there:
                        there[k] = shingles(part, k)
                q_share, r_share = (len(own & there[k]) / len(own) for k, own in self.parts[at])
                if q_share >= overlap and r_share >= overlap and score > best.get(at, (0.0,))[0]:
                    best[at] = (score, q_share, r_share)
        return [(self.ids[at], *v) for at, v in sorted(best.items())]


def item_shards(items: DataFrame, shard_items: int = 20_000) -> list[ItemIndex]:
    """One index a shard; each holds at most about ``shard_items`` items, collected one shard at a time."""
    items = items.select("item_id", "text").filter("text is not null")
    n = max(1, math.ceil(items.count() / shard_items))
    shards = (items.filter(F.pmod(F.xxhash64("item_id", "text"), F.lit(n)) == k) if n > 1 else items for k in range(n))
    return [ItemIndex([(r["item_id"], r["text"]) for r in s.collect()]) for s in shards]


def find_leaks(docs: DataFrame, items: DataFrame, threshold: float = 0.45, overlap: float = 0.5, shard_items: int = 20_000) -> DataFrame:
    """One row per document and verified item: doc_id, item_id, score, question_overlap, answer_overlap."""
    spark = docs.sparkSession

    def run(shared):
        def go(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
            index = shared.value
            for b in batches:
                rows = [(d, *h) for d, t in zip(b.column(0).to_pylist(), b.column(1).to_pylist(), strict=True) for h in index.hits(t, threshold, overlap)]
                kinds = (pa.int64(), pa.int64(), pa.float64(), pa.float64(), pa.float64())
                cols = zip(*rows, strict=True) if rows else [[]] * 5
                yield pa.RecordBatch.from_arrays([pa.array(c, k) for c, k in zip(cols, kinds, strict=True)], ["doc_id", "item_id", "score", "question_overlap", "answer_overlap"])

        return go

    out = [docs.select("doc_id", "text").mapInArrow(run(spark.sparkContext.broadcast(i)), "doc_id long, item_id long, score double, question_overlap double, answer_overlap double") for i in item_shards(items, shard_items)]
    return reduce(DataFrame.unionByName, out)


def drop_leaks(docs: DataFrame, items: DataFrame, threshold: float = 0.45, overlap: float = 0.5, shard_items: int = 20_000) -> DataFrame:
    """The rows (all columns) that hold no test item."""
    for index in item_shards(items, shard_items):
        shared = docs.sparkSession.sparkContext.broadcast(index)
        clean = F.pandas_udf(_clean(shared, threshold, overlap), "boolean")
        docs = docs.filter(clean(F.col("text")))
    return docs


def _clean(shared, threshold: float, overlap: float):
    return lambda texts: texts.map(lambda t: not shared.value.hits(t, threshold, overlap)).astype(bool)
