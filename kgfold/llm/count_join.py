"""Exact similarity join of word-shingle sets with count-vector R-trees.

Tokens (five-word shingles) are hashed into groups; a document's counts by group are a point, and the sum of the
minima of two points' coordinates bounds the overlap of their sets.

1. Documents with the same set are one class; only classes are joined.
2. Classes meet in blocks: each set's tokens are put into one global order (first three tenths of the hash range, by how
   many sets hold them, rare ones first; then the rest by hash), and two sets of similarity 4/5 must share one of their
   first floor(n/5)+1 tokens.  The numbers are counted over all classes; a token of one set alone makes no block, so a
   set with floor(n/5)+1 such tokens is alone.
   Blocks with the same members count as one.
3. Every block first tests its members against its least member: sizes, then the count bound, then the sets.
4. Blocks that still hold more than one component are searched with an R-tree over the points: node pairs whose summed
   minima of upper corners can't reach the needed overlap are cut, pairs already connected are skipped, the rest is
   bounded again with FINE groups before it leaves the task, and then verified on the sets.  Blocks over ``chunk`` members are split into chunks,
   and every pair of chunks is one task.
5. Links are joined to components by star contraction.

So a group of m near copies costs about m tests a block instead of m * m / 2, and no link between different texts is
lost: a pair is left out only where a bound excludes it or where its documents are connected already.

Defined results: null or empty text has no tokens and stands alone; fewer than five words are one token; repeated rows
share a class; rows without doc_id are linked to nothing and have no component; an empty table gives an empty table.
"""

from __future__ import annotations

import hashlib
from collections.abc import Iterator
from itertools import islice

import numpy as np
import pyarrow as pa
import xxhash
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from kgfold.kernels import components
from kgfold.llm.common import staged

WORDS, GROUPS, FINE, FANOUT = 5, 64, 512, 16
LOW = np.uint64(3 * (1 << 64) // 10)  # tokens under it are counted, about three in ten
_MIX = [np.uint64(x) for x in (0x9E3779B97F4A7C15, 0xC2B2AE3D27D4EB4F, 0x165667B19E3779F9, 0xD6E8FEB86659FD93, 0xFF51AFD7ED558CCD)]


def tokens(text: str | None) -> np.ndarray:
    """The set as sorted 64-bit hashes."""
    words = (text or "").encode().lower().split()  # bytes: only A-Z change, only ASCII white space cuts
    if not words:
        return np.zeros(0, np.uint64)
    h = np.fromiter(map(xxhash.xxh3_64_intdigest, words), np.uint64, len(words))
    if len(words) < WORDS:
        out = np.array([len(words)], np.uint64)
        for k in range(len(words)):
            out = (out ^ h[k : k + 1]) * _MIX[k]
            out ^= out >> np.uint64(29)
        return out
    n = len(words) - WORDS + 1
    out = np.full(n, 5, np.uint64)
    for k in range(WORDS):
        out = (out ^ h[k : k + n]) * _MIX[k]
        out ^= out >> np.uint64(29)
    return np.unique(out)


def needed(a, b):
    """Least overlap of sets of these sizes with similarity 4/5 or more."""
    return (4 * (a + b) + 8) // 9


def point_of(s: np.ndarray) -> bytes:
    """Counts by FINE groups, 8 bits each."""
    return np.minimum(np.bincount((s >> np.uint64(20)).astype(np.int64) % FINE, minlength=FINE), 255).astype(np.uint8).tobytes()


def counts_of(points: list[bytes], groups: int = GROUPS) -> np.ndarray:
    """Points as rows of counts by ``groups``, a divisor of FINE; counts cut at 8 bits become unbounded."""
    p = np.frombuffer(b"".join(points), np.uint8).reshape(-1, FINE // groups, groups)
    return np.where((p == 255).any(axis=1), 1 << 40, p.sum(axis=1, dtype=np.int64))


def coarse(points: list[bytes]) -> list[bytes]:
    """Points by GROUPS, 16 bits each, for the trees."""
    return [r.tobytes() for r in np.minimum(counts_of(points), 65535).astype("<u2")]


def tree_counts(points: list[bytes]) -> np.ndarray:
    p = np.frombuffer(b"".join(points), "<u2").reshape(-1, GROUPS).astype(np.int64)
    return np.where(p == 65535, 1 << 40, p)


class CountTree:
    """R-tree over count vectors, bulk-loaded: points sorted by size, packed into leaves and nodes of FANOUT."""

    def __init__(self, points: np.ndarray, sizes: np.ndarray, labels: np.ndarray):
        self.order = np.lexsort((points.argmax(axis=1), sizes))
        self.points, self.sizes, self.labels = points[self.order], sizes[self.order], labels[self.order]
        self.levels = []
        hi, lo_n, hi_n = self.points, self.sizes, self.sizes
        lab_lo = lab_hi = self.labels
        while True:
            starts = np.arange(0, len(hi), FANOUT)
            hi, lo_n, hi_n = np.maximum.reduceat(hi, starts), np.minimum.reduceat(lo_n, starts), np.maximum.reduceat(hi_n, starts)
            lab_lo, lab_hi = np.minimum.reduceat(lab_lo, starts), np.maximum.reduceat(lab_hi, starts)
            self.levels.append((hi, lo_n, hi_n, lab_lo, lab_hi))
            if len(hi) == 1:
                break

    def pairs(self, other: CountTree | None = None) -> Iterator[tuple[int, int]]:
        """Index pairs (into the input) that sizes, labels and count bound leave; within the tree, or across two trees."""
        two = self if other is None else other
        todo = [(len(self.levels) - 1, 0, len(two.levels) - 1, 0)]
        while todo:
            la, a, lb, b = todo.pop()
            ha, na, xa, pa_, qa = (x[a] for x in self.levels[la])
            hb, nb, xb, pb, qb = (x[b] for x in two.levels[lb])
            if 5 * xa < 4 * nb or 5 * xb < 4 * na or pa_ == qa == pb == qb:
                continue
            if int(np.minimum(ha, hb).sum()) < needed(int(na), int(nb)):
                continue
            if la == 0 and lb == 0:
                yield from self._leaves(a, two, b, other is None)
                continue
            if la >= lb:
                kids = range(a * FANOUT, min((a + 1) * FANOUT, len(self.levels[la - 1][0])))
                todo += [(la - 1, k, lb, b) for k in kids] if other is not None or (la, a) != (lb, b) else [(la - 1, i, la - 1, j) for i in kids for j in kids if i <= j]
            else:
                todo += [(la, a, lb - 1, k) for k in range(b * FANOUT, min((b + 1) * FANOUT, len(two.levels[lb - 1][0])))]

    def _leaves(self, a: int, two: CountTree, b: int, same: bool) -> Iterator[tuple[int, int]]:
        i, j = slice(a * FANOUT, (a + 1) * FANOUT), slice(b * FANOUT, (b + 1) * FANOUT)
        bound = np.minimum(self.points[i, None, :], two.points[None, j, :]).sum(axis=2, dtype=np.int64)
        na, nb = self.sizes[i, None], two.sizes[None, j]
        ok = (9 * bound >= 4 * (na + nb)) & (5 * na >= 4 * nb) & (5 * nb >= 4 * na) & (self.labels[i, None] != two.labels[None, j])
        if same and a == b:
            ok = np.triu(ok, 1)
        for x, y in zip(*np.nonzero(ok), strict=True):
            yield int(self.order[a * FANOUT + x]), int(two.order[b * FANOUT + y])


def _sets(docs: DataFrame) -> DataFrame:
    """doc_id, n, set_id, point and the tokens that may come first in the global order: those under ``LOW`` and, where
    these are too few, the next ones by hash."""

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for whole in batches:
            for at in range(0, whole.num_rows, 1000):
                b = whole.slice(at, 1000)
                sets = [tokens(t) for t in b.column(1).to_pylist()]
                names = [hashlib.blake2b(s.tobytes(), digest_size=16).digest() if len(s) else None for s in sets]
                first = [s[: max(int(np.searchsorted(s, LOW)), len(s) // 5 + 1)].tobytes() for s in sets]
                cols = [pa.array([len(s) for s in sets], pa.int64()), pa.array(names, pa.binary()), pa.array([point_of(s) for s in sets], pa.binary()), pa.array(first, pa.binary())]
                yield pa.RecordBatch.from_arrays([b.column(0), *cols], ["doc_id", "n", "set_id", "point", "first"])

    return docs.mapInArrow(run, "doc_id long, n long, set_id binary, point binary, first binary")


def _sheets(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
    """Classes (rep, n, point, first) packed by the hundred, so that what is said of their tokens is sent as arrays."""
    held: list[tuple] = []
    size = 0

    def flush() -> pa.RecordBatch:
        reps = np.array([r[0] for r in held], "<i8").tobytes()
        name = int.from_bytes(hashlib.blake2b(reps, digest_size=8).digest(), "little", signed=True)  # reps are unique
        row = (name, reps, np.array([r[1] for r in held], "<i8").tobytes(), b"".join(r[2] for r in held), np.array([len(r[3]) // 8 for r in held], "<i8").tobytes(), b"".join(r[3] for r in held))
        return pa.RecordBatch.from_arrays([pa.array([v], pa.int64() if k == 0 else pa.binary()) for k, v in enumerate(row)], ["sheet", "reps", "sizes", "points", "counts", "first"])

    for b in batches:
        for row in zip(*(c.to_pylist() for c in b.columns), strict=True):
            held.append(row)
            size += len(row[3])
            if size > 1 << 23:
                yield flush()
                held, size = [], 0
    if held:
        yield flush()


def _frequencies(sheets: DataFrame, at_once: int = 4_000_000) -> DataFrame:
    """sheet, said: by bucket of the hash range, in how many sets (65535: or more) each distinct low token occurs.

    Tokens are told apart by 48 bits; a collision only raises the number, for all documents alike.  A sheet sends a
    token once, however many of its sets hold it; a bucket holds about ``at_once`` tokens.
    """
    total = sheets.agg(F.coalesce(F.sum(F.length("first")), F.lit(0))).first()[0] // 8
    width = int(LOW) // max(1, -(-total // at_once)) + 1

    def deal(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for b in batches:
            for sheet, first in zip(b.column(0).to_pylist(), b.column(1).to_pylist(), strict=True):
                t, n = _low_counts(first)
                bucket = (t // np.uint64(width)).astype(np.int64)
                cuts = np.flatnonzero(np.r_[True, bucket[1:] != bucket[:-1], True]) if len(t) else np.zeros(1, np.int64)
                raw, times = t.astype(">u8").view(np.uint8).reshape(-1, 8)[:, :6].copy(), np.minimum(n, 65535).astype("<u2")
                parts = list(zip(cuts[:-1].tolist(), cuts[1:].tolist(), strict=True))
                cols = [pa.array([int(bucket[x]) for x, _ in parts], pa.int64()), pa.array([sheet] * len(parts), pa.int64()), pa.array([raw[x:y].tobytes() for x, y in parts], pa.binary()), pa.array([times[x:y].tobytes() for x, y in parts], pa.binary())]
                yield pa.RecordBatch.from_arrays(cols, ["bucket", "sheet", "tokens", "times"])

    def add(rows: pa.Table) -> pa.Table:
        blobs, times = rows.column("tokens").to_pylist(), np.frombuffer(b"".join(rows.column("times").to_pylist()), "<u2").astype(np.int64)
        raw = np.zeros((len(times), 8), np.uint8)
        raw[:, :6] = np.frombuffer(b"".join(blobs), np.uint8).reshape(-1, 6)
        _, which = np.unique(raw.view(">u8").ravel(), return_inverse=True)
        said = np.minimum(np.bincount(which, weights=times)[which], 65535).astype("<u2")
        ends = np.cumsum([len(x) // 6 for x in blobs])
        parts = [said[e - len(x) // 6 : e].tobytes() for e, x in zip(ends.tolist(), blobs, strict=True)]
        return pa.table([rows.column("bucket"), rows.column("sheet"), pa.array(parts, pa.binary())], ["bucket", "sheet", "said"])

    dealt = sheets.select("sheet", "first").mapInArrow(deal, "bucket long, sheet long, tokens binary, times binary")
    added = dealt.groupBy("bucket").applyInArrow(add, "bucket long, sheet long, said binary")
    return added.groupBy("sheet").agg(F.array_sort(F.collect_list(F.struct("bucket", "said"))).alias("said"))


def _low_counts(first: bytes) -> tuple[np.ndarray, np.ndarray]:
    t = np.frombuffer(first, "<u8")
    return np.unique(t[t < LOW], return_counts=True)


def _prefixes(sheets: DataFrame, said: DataFrame) -> DataFrame:
    """doc_id, n, fine, first: for each set that other sets could reach, its first floor(n/5)+1 tokens in the global
    order, without those of no other set."""

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for b in batches:
            for _, reps, sizes, points, counts, first, parts in zip(*(c.to_pylist() for c in b.columns), strict=True):
                low, _ = _low_counts(first)
                often = np.frombuffer(b"".join(p["said"] for p in parts or []), "<u2")
                t, n = np.frombuffer(first, "<u8"), np.frombuffer(sizes, "<i8")
                sets = np.frombuffer(counts, "<i8")
                is_low = t < LOW
                df = np.full(len(t), 1 << 20, np.int64)
                df[is_low] = often[np.searchsorted(low, t[is_low])]
                owner = np.repeat(np.arange(len(n)), sets)
                rank = np.lexsort((t, df, owner))  # low tokens by df and hash, then the others by hash
                place = np.arange(len(t)) - np.repeat(np.cumsum(sets) - sets, sets)
                keep = (place < np.repeat(n // 5 + 1, sets)) & (df[rank] > 1)
                found, own = t[rank][keep].view(np.int64), owner[keep]
                open_sets, at = np.unique(own, return_index=True)
                lists = pa.ListArray.from_arrays(pa.array(np.r_[at, len(found)].astype(np.int32)), pa.array(found))
                ids = np.frombuffer(reps, "<i8")[open_sets]
                fine = [points[k * FINE : (k + 1) * FINE] for k in open_sets.tolist()]
                yield pa.RecordBatch.from_arrays([pa.array(ids), pa.array(n[open_sets]), pa.array(fine, pa.binary()), lists], ["doc_id", "n", "fine", "first"])

    rows = sheets.join(said, "sheet", "left").select("sheet", "reps", "sizes", "points", "counts", "first", "said")
    return rows.mapInArrow(run, "doc_id long, n long, fine binary, first array<long>")


def _bounded(pairs: DataFrame, points: DataFrame) -> DataFrame:
    """Pairs (a, b) that sizes and count bound leave."""

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for b in batches:
            if b.num_rows:
                overlap = np.minimum(*(counts_of(b.column(k).to_pylist(), FINE) for k in ("pa", "pb"))).sum(axis=1)
                ok = pa.array(9 * overlap >= 4 * (b.column("na").to_numpy() + b.column("nb").to_numpy()))
                yield pa.RecordBatch.from_arrays([b.column(k).filter(ok) for k in ("a", "b")], ["a", "b"])

    one = points.select(F.col("doc_id").alias("a"), F.col("n").alias("na"), F.col("fine").alias("pa"))
    two = points.select(F.col("doc_id").alias("b"), F.col("n").alias("nb"), F.col("fine").alias("pb"))
    rows = pairs.join(one, "a").join(two, "b").filter("5 * na >= 4 * nb and 5 * nb >= 4 * na")
    return rows.select("a", "b", "na", "nb", "pa", "pb").mapInArrow(run, "a long, b long")


def _verified(pairs: DataFrame, docs: DataFrame, broadcast_rows: int = 1_000_000) -> DataFrame:
    """Pairs (a, b) whose sets really have similarity 4/5 or more."""

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for b in batches:
            known: dict[str, np.ndarray] = {}
            keep = []
            for x, y in zip(b.column("ta").to_pylist(), b.column("tb").to_pylist(), strict=True):
                for t in (x, y):
                    if t not in known:
                        known[t] = tokens(t)
                both = len(np.intersect1d(known[x], known[y], assume_unique=True))
                keep.append(9 * both >= 4 * (len(known[x]) + len(known[y])))
            yield pa.RecordBatch.from_arrays([b.column(k).filter(pa.array(keep, pa.bool_())) for k in ("a", "b")], ["a", "b"])

    ids = staged(pairs.select(F.col("a").alias("doc_id")).union(pairs.select(F.col("b").alias("doc_id"))).distinct(), "ids")
    ids = F.broadcast(ids) if ids.count() <= broadcast_rows else ids  # beyond, Spark shuffles both sides, with a Bloom filter on large scans
    texts = docs.join(ids, "doc_id", "left_semi").dropDuplicates(["doc_id"])
    rows = pairs.join(texts.select(F.col("doc_id").alias("a"), F.col("text").alias("ta")), "a").join(texts.select(F.col("doc_id").alias("b"), F.col("text").alias("tb")), "b")
    return rows.select("a", "b", "ta", "tb").mapInArrow(run, "a long, b long")


def _pairs_of(points: list[bytes], fine: np.ndarray, sizes: np.ndarray, labels: np.ndarray, left: np.ndarray, right: np.ndarray | None = None) -> list[tuple[int, int]]:
    """Index pairs that the tree and then the count bound by FINE groups leave, within ``left`` or between ``left`` and ``right``."""

    def tree(rows: np.ndarray) -> CountTree:
        return CountTree(tree_counts([points[k] for k in rows]), sizes[rows], labels[rows])

    if right is None:
        found = tree(left).pairs() if len(left) > 1 else iter(())
        right = left
    else:
        found = tree(left).pairs(tree(right)) if len(left) and len(right) else iter(())
    out: list[tuple[int, int]] = []
    while part := list(islice(found, 4096)):
        at = np.array(part, np.int64)
        a, b = left[at[:, 0]], right[at[:, 1]]
        both = np.minimum(fine[a], fine[b])
        ok = 9 * both.sum(axis=1, dtype=np.int64) >= 4 * (sizes[a] + sizes[b])
        ok |= (both == 255).any(axis=1)  # cut at 8 bits: no bound
        out += zip(a[ok].tolist(), b[ok].tolist(), strict=True)
    return out


def _fine(rows: pa.Table) -> tuple[list[bytes], np.ndarray]:
    """(coarse points, counts by FINE groups) of rows."""
    fine = rows.column("fine").to_pylist()
    return coarse(fine), np.frombuffer(b"".join(fine), np.uint8).reshape(-1, FINE)


def _pair_table(ids: np.ndarray, found: list[tuple[int, int]]) -> list[pa.Array]:
    a, b = (ids[np.array([f[k] for f in found], np.int64)] for k in (0, 1))
    return [pa.array(np.minimum(a, b), pa.int64()), pa.array(np.maximum(a, b), pa.int64())]


def _block_stream(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
    """Tree search of many blocks, whose rows come sorted by key; a block may go on in the next batch."""
    held: pa.Table | None = None

    def search(rows: pa.Table) -> pa.RecordBatch:
        keys, ids = rows.column("key").to_numpy(), rows.column("doc_id").to_numpy()
        sizes, labels, (points, fine) = rows.column("n").to_numpy(), rows.column("label").to_numpy(), _fine(rows)
        cuts = np.flatnonzero(np.r_[True, keys[1:] != keys[:-1], True])
        found: list[tuple[int, int]] = []
        for x, y in zip(cuts[:-1].tolist(), cuts[1:].tolist(), strict=True):
            if y - x > 1 and (labels[x:y] != labels[x]).any():
                found += _pairs_of(points, fine, sizes, labels, np.arange(x, y))
        return pa.RecordBatch.from_arrays(_pair_table(ids, found), ["a", "b"])

    for batch in batches:
        if batch.num_rows == 0:
            continue
        rows = pa.Table.from_batches([batch])
        rows = rows if held is None else pa.concat_tables([held, rows]).combine_chunks()
        keys = rows.column("key").to_numpy()
        last = int(np.flatnonzero(keys != keys[-1])[-1]) + 1 if keys[0] != keys[-1] else 0
        if last:
            yield search(rows.slice(0, last))
        held = rows.slice(last)
    if held is not None:
        yield search(held)


def _tree_pairs(rows: DataFrame, chunk: int) -> DataFrame:
    """Candidate pairs (a, b) of blocks (key, doc_id, n, label, fine, size): blocks up to ``chunk`` members side by
    side in sorted partitions, larger ones by pairs of chunks."""
    small = rows.filter(F.col("size") <= chunk).select("key", "doc_id", "n", "label", "fine")
    found = small.repartition("key").sortWithinPartitions("key").mapInArrow(_block_stream, "a long, b long")
    large = rows.filter(F.col("size") > chunk)
    parts = F.ceil(F.col("size") / chunk).cast("int")
    own = F.pmod(F.xxhash64("doc_id"), parts).cast("int")
    tasks = F.transform(F.sequence(F.lit(0), parts - 1), lambda k: F.struct(F.least(k, own).alias("i"), F.greatest(k, own).alias("j")))
    dealt = large.withColumn("part", own).withColumn("task", F.explode(tasks))

    def run(key: tuple, held: pa.Table) -> pa.Table:
        i, j = key[1].as_py(), key[2].as_py()
        ids, part = held.column("doc_id").to_numpy(), held.column("part").to_numpy()
        left, right = np.flatnonzero(part == i), np.flatnonzero(part == j)
        found = _pairs_of(*_fine(held), held.column("n").to_numpy(), held.column("label").to_numpy(), left, None if i == j else right)
        return pa.table(_pair_table(ids, found), ["a", "b"])

    grouped = dealt.select("key", F.col("task.i").alias("i"), F.col("task.j").alias("j"), "part", "doc_id", "n", "label", "fine")
    return found.union(grouped.groupBy("key", "i", "j").applyInArrow(run, "a long, b long")).distinct()


def linked(docs: DataFrame, chunk: int = 2000) -> DataFrame:
    """doc_id, n_shingles, component_id of every row of ``docs`` (doc_id, text)."""
    docs = docs.select("doc_id", "text")
    rows = staged(_sets(docs), "sets")
    members = rows.select("doc_id", "n", "set_id")
    known = rows.filter("set_id is not null and doc_id is not null").groupBy("set_id")
    classes = staged(members.filter("set_id is not null and doc_id is not null").groupBy("set_id").agg(F.min("doc_id").alias("rep")), "classes")
    once = known.agg(F.min("doc_id").alias("rep"), F.first("n").alias("n"), F.first("point").alias("point"), F.first("first").alias("first"))
    sheets = staged(once.select("rep", "n", "point", "first").mapInArrow(_sheets, "sheet long, reps binary, sizes binary, points binary, counts binary, first binary"), "sheets")
    sets = staged(_prefixes(sheets, _frequencies(sheets)), "open")
    points = sets.select("doc_id", "n", "fine").dropDuplicates(["doc_id"])
    keys = sets.select("doc_id", "n", F.explode("first").alias("key"))
    marks = [F.bit_xor(F.xxhash64(F.lit(k), "doc_id")).alias(f"mark{k}") for k in range(2)]
    shared = keys.groupBy("key").agg(F.count("*").alias("size"), F.min("doc_id").alias("pivot"), *marks).filter("size > 1")
    shared = shared.groupBy("size", "pivot", "mark0", "mark1").agg(F.min("key").alias("key")).select("key", "size", "pivot")  # one of the blocks with the same members
    blocks = staged(keys.join(shared, "key"), "blocks")
    stars = blocks.filter("doc_id <> pivot").select(F.col("pivot").alias("a"), F.col("doc_id").alias("b")).distinct()
    links = staged(_verified(staged(_bounded(stars, points), "stars"), docs), "links")
    label = staged(components(links, "a", "b"), "labels")
    # what a block's least member has been tested against needs no second test: blocks of two are done, pivots step out
    rest = blocks.filter("size > 2 and doc_id <> pivot").select("key", "doc_id", "n", "size")
    known = rest.join(label.withColumnRenamed("node", "doc_id"), "doc_id", "left").select("key", "doc_id", "n", "size", F.coalesce("label", "doc_id").alias("label"))
    mixed = known.groupBy("key").agg(F.min("label").alias("lo"), F.max("label").alias("hi")).filter("lo <> hi").select("key")
    open_rows = staged(known.join(mixed, "key").join(points.select("doc_id", "fine"), "doc_id"), "open")
    more = staged(_verified(staged(_tree_pairs(open_rows, chunk), "pairs"), docs), "links")
    label = staged(components(links.union(more), "a", "b"), "labels")
    # a class goes by its least doc_id; a component by the least over its classes
    by_class = classes.join(label, classes["rep"] == label["node"], "left").select("set_id", F.coalesce("label", "rep").alias("component"))
    out = members.join(by_class, "set_id", "left")
    return out.select("doc_id", F.col("n").alias("n_shingles"), F.when(F.col("doc_id").isNotNull(), F.coalesce("component", "doc_id")).alias("component_id"))
