"""Bounded-space online packing of documents into fixed windows.

Each partition streams its documents and keeps a fixed number of open windows.  A piece goes to the open window it
fits most tightly; when none has room, the fullest is topped up with the head of the piece (if the gap is worth a cut)
and emitted, and a new window opens.  What is open at the end of each partition is merged: leftovers of neighbouring
partitions are laid end to end and cut at the window size, so one window per group of partitions stays short.

Defined results: null or empty text is the end id alone; every id lies in exactly one piece; repeated rows are packed
as often as they occur; an empty table gives no pieces.
"""

from __future__ import annotations

import zlib
from bisect import bisect_left, insort
from collections.abc import Iterator

import numpy as np
import pyarrow as pa
from pyspark import TaskContext
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from kgfold.llm.common import staged
from kgfold.llm.token_units import encoder

PIECE = "doc_id long, start long, length long, ids_crc32 long, doc_tokens long, sequence_id long, offset long"
MERGED = 1 << 61  # ids of merged leftovers start here


class OpenWindows:
    """The open windows of one partition: ``place`` returns the pieces of windows that closed."""

    def __init__(self, size: int, keep: int, least_cut: int):
        self.size, self.keep, self.least_cut = size, keep, least_cut
        self.free: list[tuple[int, int]] = []  # (room, window), sorted
        self.held: dict[int, list[list]] = {}
        self.next = 0

    def _put(self, piece: list, room: int, window: int) -> None:
        doc_id, start, length, total, ids = piece
        self.held[window].append([doc_id, start, length, total, ids, self.size - room])
        if room > length:
            insort(self.free, (room - length, window))

    def _closed(self, window: int) -> list[tuple[int, list]]:
        return [(window, p) for p in self.held.pop(window)]

    def place(self, doc_id, ids: bytes) -> list[tuple[int, list]]:
        total, done, out = len(ids) // 4, 0, []
        while done < total:
            length = min(total - done, self.size)
            at = bisect_left(self.free, (length, -1))
            if at < len(self.free):
                room, window = self.free.pop(at)
            elif len(self.free) >= self.keep:
                room, window = self.free.pop(0)  # the fullest
                if room < self.least_cut:
                    out += self._closed(window)
                    continue
                length = room
            else:
                room, window = self.size, self.next
                self.held[window] = []
                self.next += 1
            self._put([doc_id, done, length, total, ids[4 * done : 4 * (done + length)]], room, window)
            if room == length:
                out += self._closed(window)
            done += length
        return out

    def rest(self) -> list[tuple[int, list]]:
        return [x for w in sorted(self.held) for x in self._closed(w)]


def _stream(path: str, end_id: int, size: int, keep: int, least_cut: int):
    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        enc, part = encoder(path), TaskContext.get().partitionId()
        windows, end = OpenWindows(size, keep, least_cut), np.array([end_id], "<u4").tobytes()

        def rows(placed: list[tuple[int, list]], open_: bool) -> pa.RecordBatch:
            cols = list(zip(*((part, w, d, s, n, zlib.crc32(i), t, at, i if open_ else None) for w, (d, s, n, t, i, at) in placed), strict=True)) or [[]] * 9
            kinds = [pa.int32(), *[pa.int64()] * 7, pa.binary()]
            return pa.RecordBatch.from_arrays([pa.array(c, k) for c, k in zip(cols, kinds, strict=True)], ["part", "win", "doc_id", "start", "length", "ids_crc32", "doc_tokens", "offset", "ids"])

        for whole in batches:
            for a in range(0, whole.num_rows, 500):
                b = whole.slice(a, 500)
                placed = []
                for doc_id, ids in zip(b.column(0).to_pylist(), enc.encode([t or "" for t in b.column(1).to_pylist()]), strict=True):
                    placed += windows.place(doc_id, ids + end)
                yield rows(placed, False)
        yield rows(windows.rest(), True)

    return run


def pack(docs: DataFrame, tokenizer_path: str, end_id: int = 1, size: int = 2048, keep: int = 32, least_cut: int = 32, group: int = 64) -> DataFrame:
    """Pieces of all ``docs`` (doc_id, text).  ``keep`` open windows a partition; leftovers of ``group`` partitions
    (at most keep * group windows) are merged by one task; gaps under ``least_cut`` ids are padded, not filled by a cut."""
    rows = staged(docs.select("doc_id", "text").mapInArrow(_stream(tokenizer_path, end_id, size, keep, least_cut), "part int, win long, doc_id long, start long, length long, ids_crc32 long, doc_tokens long, offset long, ids binary"), "packed")
    done = rows.filter("ids is null").withColumn("sequence_id", F.col("part").cast("long") * (1 << 36) + F.col("win"))

    def merge(key: tuple, held: pa.Table) -> pa.Table:
        out, at = [], 0
        for r in held.sort_by([("part", "ascending"), ("win", "ascending"), ("offset", "ascending")]).to_pylist():
            done = 0
            while done < r["length"]:
                n = min(r["length"] - done, size - at % size)
                out.append((r["doc_id"], r["start"] + done, n, zlib.crc32(r["ids"][4 * done : 4 * (done + n)]), r["doc_tokens"], MERGED + (key[0].as_py() << 32) + at // size, at % size))
                done, at = done + n, at + n
        names = [c.split()[0] for c in PIECE.split(", ")]
        return pa.table([pa.array(c, pa.int64()) for c in zip(*out, strict=True)], names)

    left = rows.filter("ids is not null").withColumn("group", (F.col("part") / group).cast("long"))
    merged = left.groupBy("group").applyInArrow(merge, PIECE)
    return done.select(*[c.split()[0] for c in PIECE.split(", ")]).unionByName(merged)
