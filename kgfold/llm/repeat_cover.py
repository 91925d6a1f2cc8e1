"""Removal of long repeated byte strings, exact, over whole corpora.

A byte goes if some string of ``LENGTH`` bytes that covers it starts anywhere else too.  As in a difference-cover
suffix array only a sample of positions is sorted by name, and equal names are refined until equality of the full
length is settled.  The sample is a cover chosen by content instead of by residue: of the K-byte strings inside a
window of LENGTH bytes the one of least hash (leftmost on ties) is the window's anchor.  Equal windows have equal
anchors at equal offsets, so comparing anchors of one name compares all equal windows, and about 2 in w + 1 positions
are sampled, where a cover by residues would need about 1 in 17 (see README for the figures).

Level 0  one row per anchor, with the range of windows that it stands for.  A name met once: nothing repeats.  A whole
         range (its windows' union, by digest) met twice: all its windows repeat.  The rest is open.
Level 1  open ranges are cut into cells on a fixed grid of offsets.  The bytes common to a cell's windows met once:
         none repeats.  The cell's union met twice: all repeat.
Level 2  the windows of cells still open, one by one.

Every level counts equal keys with map-side combination, so a passage that stands in a third of all documents costs
each task one row; one document per distinct key represents settled rows as partner of open ones.  Lists of open
anchors go to the texts by broadcast up to ``broadcast_rows`` documents, otherwise by a shuffled join.

Defined results: null text counts as empty; texts under LENGTH bytes keep all bytes; repeated rows are occurrences of
their own; null doc_id is kept; an empty table gives an empty table.
"""

from __future__ import annotations

import hashlib
from collections.abc import Iterator

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from kgfold.llm.common import staged

LENGTH = 400
K = 200
SPAN = LENGTH - K + 1  # K-byte strings in a window
CELL = 20
SLAB = 1 << 23
_BASE = 0x9E3779B97F4A7C15 | 1
_STATE: dict[str, np.ndarray] = {}


def _powers(n: int) -> tuple[np.ndarray, np.ndarray]:
    """Powers of the base and of its inverse mod 2**64, kept per worker process."""
    if len(_STATE.get("up", ())) < n:
        size = max(1 << 18, 1 << (n - 1).bit_length())
        for name, base in (("up", _BASE), ("down", pow(_BASE, -1, 1 << 64))):
            out = np.full(size, base, np.uint64)
            out[0] = 1
            _STATE[name] = np.multiply.accumulate(out)
        rng = np.random.Generator(np.random.PCG64(20))
        _STATE["bytes"] = rng.integers(1, 1 << 63, 256, dtype=np.uint64) * np.uint64(2) + np.uint64(1)
    return _STATE["up"], _STATE["down"]


class Sums:
    """Hashes of any substrings of one text by prefix sums."""

    def __init__(self, data: bytes):
        up, down = _powers(len(data) + 1)
        self.up = up
        self.sums = np.zeros(len(data) + 1, np.uint64)
        np.cumsum(_STATE["bytes"][np.frombuffer(data, np.uint8)] * up[: len(data)], out=self.sums[1:])
        self.down = down

    def of(self, start: np.ndarray, length) -> np.ndarray:
        h = (self.sums[start + length] - self.sums[start]) * self.down[start]
        h ^= h >> np.uint64(32)
        h *= np.uint64(0xD6E8FEB86659FD93)
        h ^= h >> np.uint64(29)
        return h


def anchors(data: bytes) -> tuple[np.ndarray, np.ndarray, np.ndarray, np.ndarray]:
    """(name, position, first window, last window) of each anchor of a text of LENGTH bytes or more."""
    out = []
    for base in range(0, len(data) - LENGTH + 1, SLAB):
        part = data[base : base + SLAB + LENGTH - 1]
        n = len(part) - K + 1
        at = np.arange(n)
        h = Sums(part).of(at, K)
        ranked = (h >> np.uint64(24) << np.uint64(24)) | at.astype(np.uint64)
        pad = np.full((-n) % SPAN, np.uint64(0xFFFFFFFFFFFFFFFF))
        rows = np.concatenate([ranked, pad]).reshape(-1, SPAN)
        ahead = np.minimum.accumulate(rows, axis=1).ravel()
        behind = np.minimum.accumulate(rows[:, ::-1], axis=1)[:, ::-1].ravel()
        windows = n - SPAN + 1
        least = np.minimum(behind[:windows], ahead[SPAN - 1 : SPAN - 1 + windows])
        where = (least & np.uint64((1 << 24) - 1)).astype(np.int64)
        first = np.flatnonzero(np.r_[True, where[1:] != where[:-1]])
        last = np.r_[first[1:] - 1, windows - 1]
        p = where[first]
        out.append((h[p], p + base, first + base, last + base))
    return tuple(np.concatenate(x) for x in zip(*out, strict=True))


def _digest(data: bytes) -> bytes:
    return hashlib.blake2b(data, digest_size=16).digest()


def _batch(cols: list, fields: list[tuple[str, pa.DataType]]) -> pa.RecordBatch:
    return pa.RecordBatch.from_arrays([pa.array(c, t) for c, (_, t) in zip(cols, fields, strict=True)], [f for f, _ in fields])


_L0 = [("doc_id", pa.int64()), ("at", pa.int64()), ("name", pa.int64()), ("whole", pa.binary()), ("p", pa.int64()), ("lo", pa.int64()), ("hi", pa.int64())]


def _level0(docs: DataFrame) -> DataFrame:
    """name, whole (digest of the range's union), p, lo, hi (window starts) of every anchor."""

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for whole in batches:
            for a in range(0, whole.num_rows, 200):
                b = whole.slice(a, 200)
                cols: list[list] = [[] for _ in _L0]
                for doc_id, at, text in zip(*(c.to_pylist() for c in b.columns), strict=True):
                    data = text.encode()
                    if len(data) < LENGTH:
                        continue
                    name, p, lo, hi = anchors(data)
                    lows, highs = lo.tolist(), hi.tolist()
                    for c, v in zip(cols, ([doc_id] * len(p), [at] * len(p), name.view(np.int64).tolist(), [_digest(data[x : y + LENGTH]) for x, y in zip(lows, highs, strict=True)], p.tolist(), lows, highs), strict=True):
                        c += v
                yield _batch(cols, _L0)

    return docs.select("doc_id", "at", "text").mapInArrow(run, "doc_id long, at long, name long, whole binary, p long, lo long, hi long")


_L1 = [("doc_id", pa.int64()), ("at", pa.int64()), ("common", pa.int64()), ("whole", pa.binary()), ("lo", pa.int64()), ("hi", pa.int64())]
_L2 = [("doc_id", pa.int64()), ("at", pa.int64()), ("whole", pa.binary()), ("lo", pa.int64())]


def _with_lists(docs: DataFrame, rows: DataFrame, fields: list[str], broadcast_rows: int) -> DataFrame:
    """The texts that have rows, each with its rows as a list; a list is bounded by its text's length."""
    lists = staged(rows.groupBy("doc_id", "at").agg(F.collect_list(F.struct(*fields)).alias("rows")), "lists")
    lists = lists.withColumnRenamed("doc_id", "_d").withColumnRenamed("at", "_a")
    small = lists.count() <= broadcast_rows and lists.agg(F.coalesce(F.sum(F.size("rows")), F.lit(0))).first()[0] <= 20 * broadcast_rows
    lists = F.broadcast(lists) if small else lists
    return docs.join(lists, docs["doc_id"].eqNullSafe(lists["_d"]) & (docs["at"] == lists["_a"])).select("doc_id", "at", "text", "rows")


def _level1(texts: DataFrame) -> DataFrame:
    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for whole in batches:
            for a in range(0, whole.num_rows, 200):
                b = whole.slice(a, 200)
                cols: list[list] = [[] for _ in _L1]
                for doc_id, at, text, rows in zip(*(c.to_pylist() for c in b.columns), strict=True):
                    data = text.encode()
                    p, lo, hi = (np.array([r[k] for r in rows], np.int64) for k in ("p", "lo", "hi"))
                    first, last = (p - hi) // CELL, (p - lo) // CELL
                    n = last - first + 1
                    cell = np.repeat(first, n) + np.arange(n.sum()) - np.repeat(np.cumsum(n) - n, n)
                    p, lo, hi = (np.repeat(v, n) for v in (p, lo, hi))
                    x, y = p - (cell + 1) * CELL + 1, p - cell * CELL  # least and largest window start of the cell
                    common = Sums(data).of(y, LENGTH - CELL + 1) ^ cell.astype(np.uint64) * np.uint64(_BASE)
                    inside = ((x >= lo) & (y <= hi)).tolist()
                    lows, highs = np.maximum(x, lo).tolist(), np.minimum(y, hi).tolist()
                    whole_ = [_digest(data[u : v + LENGTH]) if i else None for u, v, i in zip(lows, highs, inside, strict=True)]
                    for col, v in zip(cols, ([doc_id] * len(p), [at] * len(p), common.view(np.int64).tolist(), whole_, lows, highs), strict=True):
                        col += v
                yield _batch(cols, _L1)

    return texts.mapInArrow(run, "doc_id long, at long, common long, whole binary, lo long, hi long")


def _level2(texts: DataFrame) -> DataFrame:
    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for whole in batches:
            for a in range(0, whole.num_rows, 200):
                b = whole.slice(a, 200)
                cols: list[list] = [[] for _ in _L2]
                for doc_id, at, text, rows in zip(*(c.to_pylist() for c in b.columns), strict=True):
                    data = text.encode()
                    for x in sorted({x for r in rows for x in range(r["lo"], r["hi"] + 1)}):
                        for col, v in zip(cols, (doc_id, at, _digest(data[x : x + LENGTH]), x), strict=True):
                            col.append(v)
                yield _batch(cols, _L2)

    return texts.mapInArrow(run, "doc_id long, at long, whole binary, lo long")


def _spans(rows: DataFrame, low, high) -> DataFrame:
    return rows.select("doc_id", "at", low.alias("s"), (high + LENGTH).alias("e"))


def repeated_spans(docs: DataFrame, broadcast_rows: int = 200_000) -> DataFrame:
    """doc_id, at (hash of the text), spans: the merged byte ranges that go.  ``docs``: doc_id, text (not null), at."""
    marks = staged(_level0(docs), "anchors")
    again = marks.groupBy("name").agg(F.count("*").alias("n")).filter("n > 1").select("name")
    met = staged(marks.join(again, "name"), "met")
    ranges = staged(met.groupBy("name", "whole").agg(F.count("*").alias("n"), F.min(F.struct("doc_id", "at", "p", "lo", "hi")).alias("r")), "ranges")
    found = [_spans(met.join(ranges.filter("n > 1").select("name", "whole"), ["name", "whole"]), F.col("lo"), F.col("hi"))]
    open_names = ranges.filter("n = 1").select("name").distinct()
    taking_part = ranges.join(open_names, "name").select("r.*")
    cells = staged(_level1(_with_lists(docs, taking_part, ["p", "lo", "hi"], broadcast_rows)), "cells")
    shared = cells.groupBy("common").agg(F.count("*").alias("n")).filter("n > 1").select("common")
    shared_cells = staged(cells.join(shared, "common"), "shared")
    full = shared_cells.filter("whole is not null")
    unions = staged(full.groupBy("common", "whole").agg(F.count("*").alias("n"), F.min(F.struct("doc_id", "at", "lo", "hi")).alias("r")), "unions")
    found.append(_spans(full.join(unions.filter("n > 1").select("common", "whole"), ["common", "whole"]), F.col("lo"), F.col("hi")))
    partial = shared_cells.filter("whole is null").select("common", "doc_id", "at", "lo", "hi")
    open_cells = unions.filter("n = 1").select("common").union(partial.select("common")).distinct()
    singles = unions.select("common", "r.*").union(partial).join(open_cells, "common").select("doc_id", "at", "lo", "hi")
    windows = staged(_level2(_with_lists(docs, singles, ["lo", "hi"], broadcast_rows)), "windows")
    twice = windows.groupBy("whole").agg(F.count("*").alias("n")).filter("n > 1").select("whole")
    found.append(_spans(windows.join(twice, "whole"), F.col("lo"), F.col("lo")))

    def merge(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for b in batches:
            merged = []
            for rows in b.column(2).to_pylist():
                out: list[list[int]] = []
                for r in rows:  # sorted by start
                    if out and r["s"] <= out[-1][1]:
                        out[-1][1] = max(out[-1][1], r["e"])
                    else:
                        out.append([r["s"], r["e"]])
                merged.append(np.array(out, "<i8").tobytes())
            yield pa.RecordBatch.from_arrays([b.column(0), b.column(1), pa.array(merged, pa.binary())], ["doc_id", "at", "spans"])

    every = found[0].union(found[1]).union(found[2])
    lists = every.groupBy("doc_id", "at").agg(F.sort_array(F.collect_list(F.struct("s", "e"))).alias("rows"))  # bounded by the text's length
    return staged(lists.mapInArrow(merge, "doc_id long, at long, spans binary"), "spans")


def remove_repeats(docs: DataFrame, broadcast_rows: int = 200_000) -> DataFrame:
    """doc_id, n_bytes, n_removed, n_spans, kept (the remaining bytes) of every row of ``docs`` (doc_id, text)."""
    texts = docs.select("doc_id", F.coalesce("text", F.lit("")).alias("text")).withColumn("at", F.xxhash64("text"))
    spans = repeated_spans(texts, broadcast_rows).withColumnRenamed("doc_id", "_d").withColumnRenamed("at", "_a")
    small = spans.count() <= broadcast_rows and spans.agg(F.coalesce(F.sum(F.length("spans")), F.lit(0))).first()[0] <= 1 << 25
    joined = texts.join(F.broadcast(spans) if small else spans, texts["doc_id"].eqNullSafe(spans["_d"]) & (texts["at"] == spans["_a"]), "left")

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for b in batches:
            rows = []
            for doc_id, text, found in zip(*(c.to_pylist() for c in b.columns), strict=True):
                data, at, parts = text.encode(), 0, []
                ranges = np.frombuffer(found or b"", "<i8").reshape(-1, 2).tolist()
                for s, e in ranges:
                    parts.append(data[at:s])
                    at = e
                kept = b"".join([*parts, data[at:]])
                rows.append((doc_id, len(data), len(data) - len(kept), len(ranges), kept))
            kinds = (pa.int64(), pa.int64(), pa.int64(), pa.int64(), pa.binary())
            cols = zip(*rows, strict=True) if rows else [[]] * 5
            yield pa.RecordBatch.from_arrays([pa.array(c, k) for c, k in zip(cols, kinds, strict=True)], ["doc_id", "n_bytes", "n_removed", "n_spans", "kept"])

    return joined.select("doc_id", "text", "spans").mapInArrow(run, "doc_id long, n_bytes long, n_removed long, n_spans long, kept binary")


def digest(removed: DataFrame) -> DataFrame:
    return removed.select("doc_id", "n_bytes", "n_removed", "n_spans", F.sha2("kept", 256).alias("kept_sha256"))
