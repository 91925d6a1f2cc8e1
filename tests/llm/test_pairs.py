"""op5, op8 and op10 against brute force."""

import collections
import hashlib
import random
import re

import numpy as np

from kgfold.llm.count_join import CountTree, linked, needed
from kgfold.llm.repeat_cover import digest, remove_repeats
from kgfold.llm.weighted_sampling import fingerprints


def frame(spark, rows):
    return spark.createDataFrame(rows, "doc_id long, text string")


def near_copies(n, length, seed):
    rng = random.Random(seed)
    base, rows = [f"w{rng.randrange(400)}" for _ in range(length)], []
    for i in range(n):
        words = list(base)
        for _ in range(rng.randrange(0, 6)):
            words[rng.randrange(length)] = f"x{rng.randrange(999)}"
        rows.append((i, " ".join(words)))
    return rows


def classes_of(rows):
    sets, parent = {}, {i: i for i, _ in rows}
    for i, text in rows:
        w = [x for x in re.split("[\x20\x09-\x0d]+", re.sub("[A-Z]", lambda m: m[0].lower(), text or "")) if x]
        sets[i] = {tuple(w[k : k + 5]) for k in range(len(w) - 4)} if len(w) >= 5 else ({tuple(w)} if w else set())

    def find(x):
        while parent[x] != x:
            x = parent[x]
        return x

    for a in sets:
        for b in sets:
            if a < b and sets[a] and sets[b] and 100 * len(sets[a] & sets[b]) >= 80 * len(sets[a] | sets[b]):
                x, y = find(a), find(b)
                parent[max(x, y)] = min(x, y)
    return {i: (len(sets[i]), find(i)) for i in sets}


def test_components(spark):
    rng = random.Random(4)
    rows = near_copies(120, 80, 3) + [(500 + i, " ".join(f"y{rng.randrange(5000)}" for _ in range(rng.randrange(0, 9)))) for i in range(40)] + [(900, None), (901, "A b"), (902, "a  B"), (903, "")]
    for chunk in (2000, 20):
        got = {r["doc_id"]: (r["n_shingles"], r["component_id"]) for r in linked(frame(spark, rows), chunk=chunk).collect()}
        assert got == classes_of(rows)


def test_rows_without_id_and_empty_table(spark):
    got = linked(frame(spark, [(None, "a b c d e f"), (4, "a b c d e f"), (3, "a b c d e f")])).collect()
    assert sorted((r["doc_id"] or -1, r["component_id"]) for r in got) == [(-1, None), (3, 3), (4, 3)]
    assert linked(frame(spark, [])).collect() == []


def test_tree_leaves_no_pair_out():
    rng = np.random.default_rng(1)
    points = rng.poisson(3, (300, 64))
    points[150:] = points[:150] + rng.integers(0, 2, (150, 64))
    sizes, labels = points.sum(axis=1), np.arange(300)
    tree = CountTree(points, sizes, labels)
    want = {(i, j) for i in range(300) for j in range(i + 1, 300) if np.minimum(points[i], points[j]).sum() >= needed(sizes[i], sizes[j]) and 5 * sizes[i] >= 4 * sizes[j] and 5 * sizes[j] >= 4 * sizes[i]}
    assert {tuple(sorted(p)) for p in tree.pairs()} == want
    half = CountTree(points[:150], sizes[:150], labels[:150]), CountTree(points[150:], sizes[150:], labels[150:])
    assert {(a, b + 150) for a, b in half[0].pairs(half[1])} == {p for p in want if p[0] < 150 <= p[1]}


def removed_of(rows, length=400):
    seen, data = collections.Counter(), [(i, (t or "").encode()) for i, t in rows]
    for _, d in data:
        seen.update(d[k : k + length] for k in range(len(d) - length + 1))
    out = []
    for i, d in data:
        gone = bytearray(len(d))
        for k in range(len(d) - length + 1):
            if seen[d[k : k + length]] > 1:
                gone[k : k + length] = b"\1" * length
        kept = bytes(c for c, m in zip(d, gone, strict=True) if not m)
        out.append((i, len(d), len(d) - len(kept), len([x for x in bytes(gone).split(b"\0") if x]), hashlib.sha256(kept).hexdigest()))
    return sorted(out, key=str)


def test_repeats(spark):
    rng = random.Random(5)
    text = lambda n: "".join(rng.choice("abcdefghij klmnopé") for _ in range(n))
    a = text(1500)
    rows = [(1, a), (2, a), (3, a[200:900] + text(600)), (4, text(300) + a[100:520] + text(50) + a[600:1010]), (5, "x" * 1000), (6, text(100) + "ab" * 500), (7, None), (8, ""), (9, "y" * 400), (10, "y" * 401), (None, a), (12, text(399)), (13, a[:400]), (14, a[1:400]), (15, a[:399] + "Z"), (16, a[:700]), (16, a[:700])]
    for k in range(20):
        b = list(a)
        for _ in range(k % 4):
            b[rng.randrange(len(b))] = "Q"
        rows.append((100 + k, "".join(b)))
    for limit in (200_000, 0):  # lists by broadcast, and by shuffled join
        assert sorted(map(tuple, digest(remove_repeats(frame(spark, rows), broadcast_rows=limit)).collect()), key=str) == removed_of(rows)
    assert digest(remove_repeats(frame(spark, []))).collect() == []


def test_fingerprints(spark):
    rng = random.Random(8)
    rows = [(3 * i, " ".join(rng.choice("ABCDEFGHIJKLmnopq") + str(rng.randrange(9)) for _ in range(rng.randrange(1, 300)))) for i in range(120)] + [(1000, None), (1001, ""), (1002, "a b a"), (1005, "a b a")]
    got = {r["doc_id"]: r for r in fingerprints(frame(spark, rows)).collect()}
    texts, ids, errors = {i: t or "" for i, t in rows}, sorted((i for i, _ in rows), reverse=True), []

    def like(a, b):
        a, b = (collections.Counter(x.lower().split()) for x in (a, b))
        return sum((a & b).values()) / max(1, sum((a | b).values()))

    for k, i in enumerate(ids):
        following, own = texts[ids[(k + 1) % len(ids)]], texts[i]
        half = len(own) // 2
        edited = own[: len(own) - half] + following[:half]
        assert got[i]["n_chars"] == len(own) and got[i]["edited_sha256"] == hashlib.sha256(edited.encode()).hexdigest()
        if own:
            errors += [got[i]["near_edited"] - like(own, edited), got[i]["near_next"] - like(own, following)]
    assert abs(np.mean(errors)) < 0.03 and np.std(errors) < 0.12
    assert got[1002]["fingerprint"] == got[1005]["fingerprint"] != got[0]["fingerprint"]
    assert fingerprints(frame(spark, [])).collect() == []


def test_blocks_of_unlike_sets_send_no_pairs():
    import numpy as np
    import pyarrow as pa
    from kgfold.llm import count_join

    rng = np.random.default_rng(5)
    sets = [np.unique(rng.integers(0, 1 << 63, 3000, np.uint64)) for _ in range(40)]
    sets.append(np.unique(np.r_[sets[0][:2900], sets[1][:50]]))  # a near copy of the first
    rows = [pa.array([1] * len(sets)), pa.array(range(len(sets))), pa.array([len(s) for s in sets]), pa.array(range(len(sets))), pa.array([count_join.point_of(s) for s in sets], pa.binary())]
    found = list(count_join._block_stream(iter([pa.RecordBatch.from_arrays(rows, ["key", "doc_id", "n", "label", "fine"])])))
    assert [(p["a"], p["b"]) for b in found for p in b.to_pylist()] == [(0, 40)]
