"""Content-addressed token store.

A document's id stream (its tokens and an end id) is cut into chunks where a rolling hash over the last ids hits a
pattern, so equal passages give equal chunks wherever they stand.  A chunk is named by its digest and stored once; a
document's recipe lists the digests; Merkle roots over digests, documents and recipe files form the manifest.

Layout below the store's folder:

* ``packed/kind=c``  the unique chunks: digest, n ids, the ids (2 bytes each where the vocabulary allows, else 4)
* ``packed/kind=r``  recipes as they were made, in no order
* ``recipes``        recipes in ascending doc_id order with the global start of every document
* ``manifest``       one row: roots and totals

Texts are encoded once: chunks and recipes leave the encoding job as rows of one stream, and one shuffle with map-side
combination keeps the first copy of each chunk.  Reading never moves chunk bytes: each chunk is checked against its
name and reduced to a CRC where it lies, and the CRCs of a document are combined algebraically.

Defined results: null or empty text gives the end id alone; repeated rows keep one recipe each; null doc_id sorts
first; an empty table gives an empty store.
"""

from __future__ import annotations

import hashlib
import zlib
from collections.abc import Iterator

import numpy as np
import pyarrow as pa
from pyspark import TaskContext
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from kgfold.llm.common import running_start
from kgfold.llm.token_units import encoder

WINDOW, MEAN_BITS, LEAST, MOST = 8, 8, 64, 1024
DIGEST = 16
_POLY = 0xEDB88320


def rolling(ids: np.ndarray) -> np.ndarray:
    """Hash of the WINDOW ids that end at each position (64-bit wrap-around)."""
    mixed = ids.astype(np.uint64) + np.uint64(1)
    mixed *= np.uint64(0x9E3779B97F4A7C15)
    mixed ^= mixed >> np.uint64(31)
    mixed *= np.uint64(0xD6E8FEB86659FD93)
    out = mixed.copy()
    for k in range(1, WINDOW):
        mixed *= np.uint64(0x2545F4914F6CDD1D)
        out[k:] += mixed[:-k]
    return out


def cuts(ids: np.ndarray, bounds: np.ndarray) -> list[list[int]]:
    """Chunk ends of each document; ``bounds`` are the documents' limits within ``ids``."""
    hits = np.flatnonzero(rolling(ids) >> np.uint64(64 - MEAN_BITS) == 0) + 1
    out = []
    for a, b in zip(bounds[:-1].tolist(), bounds[1:].tolist(), strict=True):
        ends, last = [], a
        if b - a > LEAST:
            for h in hits[np.searchsorted(hits, a + LEAST) : np.searchsorted(hits, b)].tolist():
                while h - last > MOST:
                    last += MOST
                    ends.append(last)
                if h - last >= LEAST:
                    last = h
                    ends.append(h)
            while b - last > MOST:
                last += MOST
                ends.append(last)
        if last < b:
            ends.append(b)
        out.append(ends)
    return out


def merkle(digests: list[bytes]) -> bytes:
    """Root of a binary hash tree; inner nodes and leaves are hashed apart."""
    level = [hashlib.blake2b(b"\0" + d, digest_size=DIGEST).digest() for d in digests] or [bytes(DIGEST)]
    while len(level) > 1:
        level = [hashlib.blake2b(b"\1" + b"".join(level[i : i + 2]), digest_size=DIGEST).digest() for i in range(0, len(level), 2)]
    return level[0]


def _times(a: np.ndarray, b: np.ndarray) -> np.ndarray:
    """Product of CRC polynomials (reflected), elementwise."""
    a, b, out = a.astype(np.uint32), b.astype(np.uint32), np.zeros(np.broadcast(a, b).shape, np.uint32)
    for bit in range(31, -1, -1):
        out ^= np.where(a >> np.uint32(bit) & np.uint32(1), b, np.uint32(0))
        b = np.where(b & np.uint32(1), b >> np.uint32(1) ^ np.uint32(_POLY), b >> np.uint32(1))
    return out


def shifted_crc(crc: np.ndarray, after: np.ndarray) -> np.ndarray:
    """What a piece adds to a whole's CRC-32 when ``after`` bytes follow it; the whole's CRC is the xor over its pieces."""
    power, square, left = np.full(crc.shape, 1 << 31, np.uint32), np.uint32(1 << 23), after.astype(np.uint64)  # x^0, x^8
    while left.any():
        power = np.where(left & np.uint64(1), _times(power, np.full(crc.shape, square, np.uint32)), power)
        square = _times(np.array([square]), np.array([square]))[0]
        left >>= np.uint64(1)
    return _times(power, crc)


def _rows(path: str, end_id: int, width: int):
    kind = "<u2" if width == 2 else "<u4"
    names = ["kind", "key", "doc_id", "n", "data"]

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        enc, part, row, seen = encoder(path), TaskContext.get().partitionId(), 0, set()
        end = np.array([end_id], "<u4").tobytes()
        for whole in batches:
            for at in range(0, whole.num_rows, 500):
                b = whole.slice(at, 500)
                doc_ids, texts = b.column(0).to_pylist(), [t or "" for t in b.column(1).to_pylist()]
                streams = [x + end for x in enc.encode(texts)]
                ids = np.frombuffer(b"".join(streams), "<u4")
                bounds = np.concatenate([[0], np.cumsum([len(s) // 4 for s in streams])]).astype(np.int64)
                raw = ids.astype(kind).tobytes()
                out: list[tuple] = []
                for doc_id, ends, first in zip(doc_ids, cuts(ids, bounds), bounds[:-1].tolist(), strict=True):
                    recipe, last = [], first
                    for e in ends:
                        chunk = raw[last * width : e * width]
                        name = hashlib.blake2b(chunk, digest_size=DIGEST).digest()
                        recipe.append(name + (e - last).to_bytes(4, "little"))
                        if name not in seen:
                            seen.add(name)
                            out.append(("c", name, None, e - last, chunk))
                        last = e
                    out.append(("r", part.to_bytes(8, "big") + row.to_bytes(8, "big"), doc_id, last - first, b"".join(recipe)))
                    row += 1
                if len(seen) > 1_000_000:  # only saves work: the shuffle drops copies anyway
                    seen.clear()
                yield pa.RecordBatch.from_arrays([pa.array(c, t) for c, t in zip(zip(*out, strict=True), (pa.string(), pa.binary(), pa.int64(), pa.int32(), pa.binary()), strict=True)], names)

    return run


def write_store(docs: DataFrame, folder: str, tokenizer_path: str, end_id: int = 1) -> None:
    """Encode ``docs`` (doc_id, text) and write chunks, ordered recipes and manifest below ``folder``."""
    spark = docs.sparkSession
    from tokenizers import Tokenizer

    width = 2 if Tokenizer.from_file(tokenizer_path).get_vocab_size() <= 1 << 16 and end_id < 1 << 16 else 4
    rows = docs.select("doc_id", "text").mapInArrow(_rows(tokenizer_path, end_id, width), "kind string, key binary, doc_id long, n int, data binary")
    once = rows.groupBy("kind", "key").agg(F.first("doc_id").alias("doc_id"), F.first("n").alias("n"), F.first("data").alias("data"))
    once.write.partitionBy("kind").option("compression", "zstd").parquet(f"{folder}/packed")
    made = spark.read.schema("kind string, key binary, doc_id long, n int, data binary").parquet(f"{folder}/packed").filter("kind = 'r'")
    starts = running_start(made.select("doc_id", F.col("key").alias("row_key"), F.col("n").cast("long").alias("n_tokens")), "n_tokens", tie=("row_key",))
    recipes = starts.join(made.select(F.col("key").alias("row_key"), F.col("data").alias("chunks")), "row_key")

    def rooted(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for b in batches:
            roots = [merkle(_entries(c)) for c in b.column("chunks").to_pylist()]
            yield pa.RecordBatch.from_arrays([*b.columns, pa.array(roots, pa.binary())], [*b.schema.names, "root"])

    recipes = recipes.select("doc_id", "start", "n_tokens", "row_key", "chunks")
    rooted_rows = recipes.mapInArrow(rooted, "doc_id long, start long, n_tokens long, row_key binary, chunks binary, root binary")
    n = int(spark.conf.get("spark.sql.shuffle.partitions"))
    ordered = rooted_rows.repartitionByRange(n, F.col("start")).sortWithinPartitions("start")
    ordered.write.option("compression", "zstd").parquet(f"{folder}/recipes")
    top, docs_in, ids_in = _recipe_root(spark, folder, recompute=False)
    row = (top, docs_in, ids_in, width, end_id, tokenizer_path)
    spark.createDataFrame([row], "root string, docs long, ids long, width int, end_id int, tokenizer string").coalesce(1).write.json(f"{folder}/manifest")


def read_recipes(spark: SparkSession, folder: str) -> DataFrame:
    return spark.read.schema("doc_id long, start long, n_tokens long, row_key binary, chunks binary, root binary").parquet(f"{folder}/recipes")


def read_chunks(spark: SparkSession, folder: str) -> DataFrame:
    return spark.read.schema("kind string, key binary, doc_id long, n int, data binary").parquet(f"{folder}/packed").filter("kind = 'c'").select(F.col("key").alias("digest"), "n", "data")


def _entries(chunks: bytes) -> list[bytes]:
    return [chunks[i : i + DIGEST + 4] for i in range(0, len(chunks), DIGEST + 4)]


def _recipe_root(spark: SparkSession, folder: str, recompute: bool) -> tuple[str, int, int]:
    """Root, documents and ids of the recipes as they lie in the files, however the reader splits these.

    A document's leaf binds its root, doc_id, start and length.  With ``recompute`` roots come from the recipes, and one
    that differs from the stored root fails the job.
    """

    def leaves(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for b in batches:
            out = []
            for doc, start, n, chunks, root in zip(*(c.to_pylist() for c in b.columns[1:]), strict=True):
                if recompute:
                    entries = _entries(chunks)
                    if merkle(entries) != root or sum(int.from_bytes(e[DIGEST:], "little") for e in entries) != n:
                        raise ValueError(f"the recipe of the document at {start} doesn't fit its root")
                out.append(hashlib.blake2b(repr((doc, start, n)).encode() + root, digest_size=DIGEST).digest())
            yield pa.RecordBatch.from_arrays([b.column(0), b.column(2), b.column(3), pa.array(out, pa.binary())], ["file", "start", "n_tokens", "leaf"])

    def file_root(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for b in batches:
            roots = [merkle([x["leaf"] for x in docs]) for docs in b.column(3).to_pylist()]
            yield pa.RecordBatch.from_arrays([*b.columns[:3], pa.array(roots, pa.binary())], ["first", "docs", "ids", "root"])

    rows = read_recipes(spark, folder).select(F.input_file_name().alias("file"), "doc_id", "start", "n_tokens", "chunks", "root")
    rows = rows.mapInArrow(leaves, "file string, start long, n_tokens long, leaf binary")
    files = rows.groupBy("file").agg(F.min("start").alias("first"), F.count("*").alias("docs"), F.sum("n_tokens").alias("ids"), F.array_sort(F.collect_list(F.struct("start", "leaf"))).alias("leaves"))
    parts = files.drop("file").mapInArrow(file_root, "first long, docs long, ids long, root binary").collect()  # one row per recipe file
    parts.sort(key=lambda p: p["first"])
    return merkle([bytes(p["root"]) for p in parts]).hex(), sum(p["docs"] for p in parts), sum(p["ids"] for p in parts)


def _verified_width(spark: SparkSession, folder: str) -> int:
    """Bytes per id, after the recipes were proved against the manifest."""
    kept = spark.read.schema("root string, docs long, ids long, width int").json(f"{folder}/manifest").first()
    if kept is None or (kept["root"], kept["docs"], kept["ids"]) != (found := _recipe_root(spark, folder, recompute=True)):
        raise ValueError(f"recipes don't fit the manifest: {found} found, {tuple(kept)[:3]} written" if kept else "the manifest is empty")
    return kept["width"]


def _pieces(recipes: DataFrame) -> DataFrame:
    """One row per chunk of a document: row_key, at (ids before it in the document), after (ids behind it), digest."""

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for b in batches:
            out: list[tuple] = []
            for key, doc, start, total, chunks in zip(*(c.to_pylist() for c in b.columns), strict=True):
                at = 0
                for i in range(0, len(chunks), DIGEST + 4):
                    size = int.from_bytes(chunks[i + DIGEST : i + DIGEST + 4], "little")
                    out.append((key, doc, start, total, at, total - at - size, chunks[i : i + DIGEST]))
                    at += size
            kinds = (pa.binary(), pa.int64(), pa.int64(), pa.int64(), pa.int64(), pa.int64(), pa.binary())
            cols = zip(*out, strict=True) if out else [[]] * 7
            yield pa.RecordBatch.from_arrays([pa.array(c, t) for c, t in zip(cols, kinds, strict=True)], ["row_key", "doc_id", "start", "n_tokens", "at", "after", "digest"])

    return recipes.select("row_key", "doc_id", "start", "n_tokens", "chunks").mapInArrow(run, "row_key binary, doc_id long, start long, n_tokens long, at long, after long, digest binary")


def read_documents(spark: SparkSession, folder: str) -> DataFrame:
    """Rebuild every document from the files: doc_id, start, ids (array).

    Recipes that don't fit the manifest, and chunks that are missing or don't match their digest, fail the job.
    """
    width = _verified_width(spark, folder)
    kind = "<u2" if width == 2 else "<u4"

    def ids(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for b in batches:
            for parts in b.column(2).to_pylist():
                for p in parts:
                    if p["data"] is None or hashlib.blake2b(p["data"], digest_size=DIGEST).digest() != p["digest"]:
                        raise ValueError(f"chunk {p['digest'].hex()} is {'missing' if p['data'] is None else 'damaged'}")
            joined = [np.frombuffer(b"".join(p["data"] for p in parts), kind).tolist() for parts in b.column(2).to_pylist()]
            yield pa.RecordBatch.from_arrays([b.column(0), b.column(1), pa.array(joined, pa.list_(pa.int64()))], ["doc_id", "start", "ids"])

    parts = _pieces(read_recipes(spark, folder)).join(read_chunks(spark, folder), "digest", "left")
    whole = parts.groupBy("row_key").agg(F.first("doc_id").alias("doc_id"), F.first("start").alias("start"), F.array_sort(F.collect_list(F.struct("at", "data", "digest"))).alias("parts"))
    return whole.select("doc_id", "start", "parts").mapInArrow(ids, "doc_id long, start long, ids array<long>")


def read_checks(spark: SparkSession, folder: str) -> DataFrame:
    """From the files alone: doc_id, start, n_tokens and the CRC-32 of each document's ids (4 bytes each).

    A chunk whose bytes don't match its digest, or that is missing, and recipes that don't fit the manifest fail the job.
    """
    width = _verified_width(spark, folder)
    kind = "<u2" if width == 2 else "<u4"

    def sums(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for b in batches:
            names, data = b.column(0).to_pylist(), b.column(1).to_pylist()
            for name, d in zip(names, data, strict=True):
                if hashlib.blake2b(d, digest_size=DIGEST).digest() != name:
                    raise ValueError(f"chunk {name.hex()} is damaged")
            crcs = [zlib.crc32(np.frombuffer(d, kind).astype("<u4").tobytes()) for d in data]
            yield pa.RecordBatch.from_arrays([b.column(0), pa.array(crcs, pa.int64())], ["digest", "crc"])

    def shift(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for b in batches:
            if b.column("crc").null_count:
                raise ValueError("a recipe names a chunk that the store lacks")
            moved = shifted_crc(b.column("crc").to_numpy().astype(np.uint32), b.column("after").to_numpy() * 4)
            cols = [b.column(c) for c in ("row_key", "doc_id", "start", "n_tokens")]
            yield pa.RecordBatch.from_arrays([*cols, pa.array(moved.astype(np.int64))], ["row_key", "doc_id", "start", "n_tokens", "part"])

    crcs = read_chunks(spark, folder).select("digest", "data").mapInArrow(sums, "digest binary, crc long")
    parts = _pieces(read_recipes(spark, folder)).join(crcs, "digest", "left").select("row_key", "doc_id", "start", "n_tokens", "after", "crc")
    moved = parts.mapInArrow(shift, "row_key binary, doc_id long, start long, n_tokens long, part long")
    return moved.groupBy("row_key", "doc_id", "start", "n_tokens").agg(F.bit_xor("part").alias("ids_crc32")).select("doc_id", "start", "n_tokens", "ids_crc32")
