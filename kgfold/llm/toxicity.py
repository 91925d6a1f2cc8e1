"""Toxicity by fuzzy lexicon matching in context.

The lexicon is a trie.  Its entries are whole words or open stems (any ending), learned from labelled documents: terms
whose document frequency among toxic rows is far above that among clean rows.  A token is matched by running the
intersection of the trie with Levenshtein automata of its terms: a state is the set of (trie node, edits so far) that
the characters read can have led to, and states and transitions are kept as they are met, so most tokens die after two
or three table lookups.  Misspelt terms are found within ``edits_for`` their length.

Each hit gets a context score from a window of tokens around it: quotation marks, reporting words and mentions of the
word as a word speak for quotation; second person and repeated hits speak for abuse.  A small logistic model over
these features, fitted on the same labelled rows, gives the score.

Only the labels come from a bounded sample (``max_rows`` training rows, chosen by hash); scoring covers every token of
every text.  Defined results: null or empty text scores as a text without hits; an empty training set gives the
fallback model; repeated rows give repeated results; an empty table gives an empty table.
"""

from __future__ import annotations

import math
import re
from collections import Counter
from collections.abc import Iterator
from dataclasses import dataclass, field

import numpy as np
import pyarrow as pa
from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

from kgfold.llm.common import staged

_TOKEN = re.compile(r"[^\W_]+(?:['’][^\W_]+)*|[\"“”«»„‘]")
_WORD = re.compile(r"[^\W_]+(?:['’][^\W_]+)*")
QUOTES = frozenset("\"“”«»„‘")
REPORTING = frozenset("said says wrote writes called calls term word words quote quoted quoting slur insult insults phrase meaning definition sagte schrieb nannte wort zitat dit écrit appelé mot citation dijo escribió llamó palabra cita".split())
SECOND = frozenset("you your you're youre u ur du dich dein deine ihr tu te toi ton vous votre tú ti usted eres".split())
WINDOW = 6
FEATURES = ("bias", "hits", "weight", "fuzzy", "quoted", "directed", "density")
FALLBACK = (-4.0, 2.0, 1.0, 1.0, -2.0, 1.0, 1.0)


def edits_for(length: int, open_stem: bool) -> int:
    """Edits allowed for a term of this length: short terms and short stems must match exactly."""
    if open_stem:
        return 1 if length >= 8 else 0
    return 0 if length < 5 else 1 if length < 9 else 2


class FuzzyLexicon:
    """terms: {term: weight}; a term that ends in * is an open stem."""

    def __init__(self, terms: dict[str, float]):
        self.weights: list[tuple[str, float]] = sorted(terms.items())
        self.kids: list[dict[str, int]] = [{}]
        self.ends: list[tuple[int, bool, int] | None] = [None]  # entry, open, edits allowed
        self.room = [0]  # most edits any term below allows
        for i, (term, _) in enumerate(self.weights):
            word, open_ = term.rstrip("*"), term.endswith("*")
            allowed, at = edits_for(len(word), open_), 0
            self.room[0] = max(self.room[0], allowed)
            for c in word:
                if c not in self.kids[at]:
                    self.kids[at][c] = len(self.kids)
                    self.kids.append({})
                    self.ends.append(None)
                    self.room.append(0)
                at = self.kids[at][c]
                self.room[at] = max(self.room[at], allowed)
            if self.ends[at] is None or open_:
                self.ends[at] = (i, open_, allowed)
        self.table: list[dict[str, int]] = []
        self.accept: list[tuple[int, int] | None] = []  # at the end of a token: (entry, edits)
        self.closed: list[tuple[int, int] | None] = []  # as soon as reached: an open stem
        self.names: dict[frozenset, int] = {}
        self.sets: list[frozenset] = []
        self.start = self._state({(0, 0)})

    def _state(self, members: set[tuple[int, int]]) -> int:
        todo, best = list(members), {}
        while todo:  # deletions from the term cost an edit and read nothing
            node, e = todo.pop()
            if e > self.room[node] or best.get(node, 99) <= e:
                continue
            best[node] = e
            todo += [(k, e + 1) for k in self.kids[node].values()]
        key = frozenset(best.items())
        if key not in self.names:
            self.names[key] = len(self.sets)
            self.sets.append(key)
            self.table.append({})
            ends = [(e, self.ends[n]) for n, e in best.items() if self.ends[n] is not None and e <= self.ends[n][2]]
            self.accept.append(min(((e, x[0]) for e, x in ends), default=None))
            self.closed.append(min(((e, x[0]) for e, x in ends if x[1]), default=None))
        return self.names[key]

    def _step(self, state: int, c: str) -> int:
        moved = set()
        for node, e in self.sets[state]:
            for k, child in self.kids[node].items():
                moved.add((child, e if k == c else e + 1))
            moved.add((node, e + 1))  # an extra character in the token
        new = self._state(moved) if moved else -1
        new = -1 if new >= 0 and not self.sets[new] else new
        if len(self.table[state]) < 4096:
            self.table[state][c] = new
        return new

    def match(self, token: str) -> tuple[int, int] | None:
        """(edits, entry) of the best match of the lower-cased token."""
        state, found = self.start, None
        for c in token:
            nxt = self.table[state].get(c)
            state = self._step(state, c) if nxt is None else nxt
            if state < 0:
                return found
            hit = self.closed[state]
            if hit is not None and (found is None or hit < found):
                found = hit
        hit = self.accept[state]
        return hit if hit is not None and (found is None or hit < found) else found


@dataclass
class Scorer:
    lexicon: FuzzyLexicon
    coefficients: tuple[float, ...] = FALLBACK
    max_known: int = 400_000
    clean: set[str] = field(default_factory=set)

    def __getstate__(self):
        return {"terms": dict(self.lexicon.weights), "coefficients": self.coefficients, "max_known": self.max_known}

    def __setstate__(self, s):
        self.__init__(FuzzyLexicon(s["terms"]), s["coefficients"], s["max_known"])

    def features(self, text: str | None) -> list[float]:
        low = (text or "").lower()
        words = set(_WORD.findall(low))
        hits: dict[str, tuple[int, int]] = {}
        match, clean = self.lexicon.match, self.clean
        for w in words.difference(clean):
            m = match(w)
            if m is None:
                clean.add(w)
            else:
                hits[w] = m
        if len(clean) > self.max_known:  # a bounded memory of tokens that match nothing
            clean.clear()
        out = [1.0, 0.0, 0.0, 0.0, 0.0, 0.0, 0.0]
        if not hits:
            return out
        tokens = _TOKEN.findall(low)
        at = [i for i, t in enumerate(tokens) if t in hits]
        directed = quoted = fuzzy = weight = 0.0
        for i in at:
            edits, entry = hits[tokens[i]]
            around = tokens[max(0, i - WINDOW) : i] + tokens[i + 1 : i + 1 + WINDOW]
            tight = tokens[max(0, i - 2) : i], tokens[i + 1 : i + 3]
            is_quoted = (bool(QUOTES & set(tight[0])) and bool(QUOTES & set(tight[1]))) + 0.5 * bool(REPORTING & set(around))
            quoted += min(1.0, is_quoted)
            directed += bool(SECOND & set(around))
            fuzzy += edits > 0
            weight += self.lexicon.weights[entry][1] / (1 + edits)
        n = len(at)
        return [1.0, math.log1p(n), math.log1p(max(0.0, weight)), fuzzy / n, quoted / n, directed / n, math.log1p(1000.0 * n / max(1, len(tokens)))]

    def score(self, text: str | None) -> float:
        z = sum(a * b for a, b in zip(self.features(text), self.coefficients, strict=True))
        return 1.0 / (1.0 + math.exp(-max(-50.0, min(50.0, z))))


def held_out(doc_id: Column) -> Column:
    """Rows whose labels are never learned from."""
    return F.crc32(doc_id.cast("string")) % 5 == 0


def training_rows(docs: DataFrame, labels: DataFrame, max_rows: int) -> DataFrame:
    """At most about ``max_rows`` labelled rows outside the held-out fifth, chosen by a hash of the id; staged."""
    known = labels.select("doc_id", "toxic").filter("toxic is not null and doc_id is not null").filter(~held_out(F.col("doc_id")))
    known = known.groupBy("doc_id").agg(F.max("toxic").alias("toxic"))
    n = known.count()
    if n > max_rows:
        known = known.filter(F.pmod(F.xxhash64("doc_id", F.lit(77)), F.lit(1 << 20)) < int((1 << 20) * max_rows / n))
    return staged(docs.select("doc_id", "text").join(known, "doc_id").select("text", "toxic"), "training")


def _terms_of(text: str | None) -> set[str]:
    words = set(_WORD.findall((text or "").lower()))
    return {w for w in words if 3 <= len(w) <= 30} | {f"{w[:k]}*" for w in words for k in range(4, min(10, len(w)) + 1)}


def learn_terms(rows: DataFrame, least_docs: int = 3, least_gain: float = 3.0, most: int = 20_000) -> dict[str, float]:
    """Words and stems (4 to 10 characters) that explain the toxic rows, with their log-odds.

    Candidates stand in ``least_docs`` distinct toxic texts at least, with odds over exp(``least_gain``); the ``most``
    most frequent are looked at.  Of these, terms are taken greedily by the toxic texts they explain that no earlier
    term explains (so a word that merely shares its texts with an insult is not taken), then those about as frequent
    as the terms taken.
    """

    def count(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for b in batches:
            for a in range(0, b.num_rows, 200):
                seen: Counter = Counter()
                toxic: Counter = Counter()
                part = b.slice(a, 200)
                for text, label in zip(part.column(0).to_pylist(), part.column(1).to_pylist(), strict=True):
                    terms = _terms_of(text)
                    seen.update(terms)
                    if label:
                        toxic.update(terms)
                keys = list(seen)
                yield pa.RecordBatch.from_arrays([pa.array(keys, pa.string()), pa.array([seen[k] for k in keys], pa.int64()), pa.array([toxic[k] for k in keys], pa.int64())], ["term", "n", "t"])

    texts = rows.groupBy("text").agg(F.max((F.col("toxic") == 1).cast("int")).alias("toxic"))
    totals = texts.agg(F.count("*").alias("n"), F.sum("toxic").alias("t")).first()
    n_toxic, n_clean = totals["t"] or 0, totals["n"] - (totals["t"] or 0)
    if not n_toxic or not n_clean:
        return {}
    counts = texts.select("text", "toxic").mapInArrow(count, "term string, n long, t long").groupBy("term").agg(F.sum("n").alias("n"), F.sum("t").alias("t"))
    gain = F.log(((F.col("t") + 0.5) / (n_toxic + 1)) / ((F.col("n") - F.col("t") + 0.5) / (n_clean + 1)))
    best = counts.filter(F.col("t") >= least_docs).withColumn("gain", gain).filter(F.col("gain") >= least_gain).orderBy(F.desc("t"), "term").limit(most).collect()  # at most `most` rows
    found = {r["term"]: (r["t"], r["gain"]) for r in best}

    def held(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for b in batches:
            yield pa.RecordBatch.from_arrays([pa.array([sorted(_terms_of(t) & found.keys()) for t in b.column(0).to_pylist()], pa.list_(pa.string()))], ["terms"])

    rest = [set(r["terms"]) for r in texts.filter("toxic = 1").select("text").mapInArrow(held, "terms array<string>").collect()]  # toxic rows of the bounded sample
    kept: dict[str, float] = {}
    while True:
        covered = Counter(t for terms in rest for t in terms)
        if not covered:
            break
        top = max(covered, key=lambda t: (covered[t] * found[t][1], len(t.rstrip("*")), not t.endswith("*"), t))
        if covered[top] < least_docs:
            break
        kept[top] = float(found[top][1])
        rest = [terms for terms in rest if top not in terms]
    if kept:
        usual = sorted(found[t][0] for t in kept)[len(kept) // 2]
        for term in sorted(found, key=lambda t: (-found[t][0], -len(t.rstrip("*")), t.endswith("*"), t)):
            word = term.rstrip("*")
            related = any(word.startswith(k.rstrip("*")) or k.startswith(word) for k in kept)
            if not related and found[term][0] >= 0.3 * usual and found[term][1] >= least_gain + 1:
                kept[term] = float(found[term][1])
    return kept


def fit(rows: DataFrame, lexicon: FuzzyLexicon) -> tuple[float, ...]:
    """Coefficients of the logistic model over FEATURES (ridge, Newton steps) on the staged training rows."""
    scorer = Scorer(lexicon)

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for b in batches:
            table = [scorer.features(t) for t in b.column(0).to_pylist()]
            yield pa.RecordBatch.from_arrays([pa.array(table, pa.list_(pa.float64())), b.column(1)], ["x", "y"])

    grouped = rows.select("text", (F.col("toxic") == 1).cast("double").alias("y")).mapInArrow(run, "x array<double>, y double").groupBy("x", "y").count().collect()  # of the bounded sample
    if not grouped:
        return FALLBACK
    x, y, w = np.array([r["x"] for r in grouped]), np.array([r["y"] for r in grouped]), np.array([float(r["count"]) for r in grouped])
    beta = np.zeros(x.shape[1])
    ridge = np.full(x.shape[1], 0.5)
    for _ in range(30):
        p = 1 / (1 + np.exp(-np.clip(x @ beta, -30, 30)))
        grad = x.T @ (w * (y - p)) - ridge * beta
        hess = (x.T * (w * np.maximum(p * (1 - p), 1e-6))) @ x + np.diag(ridge)
        move = np.linalg.solve(hess, grad)
        beta += move
        if np.abs(move).max() < 1e-8:
            break
    return tuple(beta.tolist())


def train(docs: DataFrame, labels: DataFrame, max_rows: int = 20_000) -> Scorer:
    rows = training_rows(docs, labels, max_rows)
    terms = learn_terms(rows)
    if not terms:
        return Scorer(FuzzyLexicon({}))
    lexicon = FuzzyLexicon(terms)
    return Scorer(lexicon, fit(rows, lexicon))


def score(docs: DataFrame, scorer: Scorer) -> DataFrame:
    """doc_id, held_out, score, predicted for every row.  Row-wise: no shuffle."""

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for b in batches:
            scores = [scorer.score(t) for t in b.column(2).to_pylist()]
            yield pa.RecordBatch.from_arrays([b.column(0), b.column(1), pa.array(scores), pa.array([int(s >= 0.5) for s in scores], pa.int32())], ["doc_id", "held_out", "score", "predicted"])

    rows = docs.select("doc_id", F.coalesce(held_out(F.col("doc_id")), F.lit(False)).alias("held_out"), "text")
    return rows.mapInArrow(run, "doc_id long, held_out boolean, score double, predicted int")


def drop_toxic(docs: DataFrame, scorer: Scorer) -> DataFrame:
    """The rows (all columns) that score under 0.5."""
    flag = F.pandas_udf(lambda texts: texts.map(lambda t: scorer.score(t) < 0.5), "boolean")
    return docs.filter(flag(F.col("text")))
