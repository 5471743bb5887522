"""Toxicity: a learned lexicon, Levenshtein automata over its trie, and context windows.

Fitting takes a bounded sample of labelled rows (``max_train``, by the hash of
doc_id). A word enters the lexicon where it stands in far more different
contexts (word before, word after) of toxic than of other texts; contexts
rather than texts are counted, so copies of one text make no term. Misspelled
terms are found by walking the lexicon's trie with a Levenshtein automaton, one
edit from five letters and two from twelve; spellings that the sample's clean
texts also use are no misspellings. Each hit is read in its window: inside
quotation marks or after a word of reporting it is a quotation, next to an
address it is aimed. A logistic model over the logarithms of these counts gives
the score. Labels are read from training rows only; lang, source and doc_id
are no inputs of a score.

Defined cases: null or empty text has no hits and gets the score of such texts;
rows without a label only take no part in fitting; with no labelled row, or
none of one class, the score is the smoothed share of toxic rows; very long texts
are scanned whole; repeated rows
are scored alike; a null doc_id is not held out; extra columns are ignored.
"""

from __future__ import annotations

import re
from dataclasses import dataclass, field

import numpy as np
import pyarrow as pa
import xxhash
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

_WORD = re.compile(r"[^\W_]+(?:[*@$][^\W_]+)*|[\"“”„«»‹›]")
#: Quotation marks; words of reporting and of address in the four languages.
QUOTES = frozenset("\"“”„«»‹›")
REPORTING = frozenset("said says called call calls quote quoted word words term wrote writes reported dit mot appelé sagte sagt nannte wort palabra dijo llamó".split())
ADDRESS = frozenset("you your youre u tu te toi vous du dich dir ihr usted tú eres vosotros".split())
WINDOW = 8
NONE, EXACT, NEAR = 0, 1, 2


def edits(term_length: int) -> int:
    return 0 if term_length < 5 else 1 if term_length < 12 else 2


class Node:
    __slots__ = ("least", "longest", "next", "term")

    def __init__(self):
        self.next: dict[str, Node] = {}
        self.term, self.least, self.longest = None, 1 << 30, 0


class Trie:
    """The lexicon's trie; ``near`` intersects it with the automaton of a word."""

    def __init__(self, terms):
        self.root = Node()
        self.terms = frozenset(terms)
        # with k edits one of k + 1 parts of a term stays whole, at most k places off: other words need no walk
        parts: set[tuple[int, str]] = set()
        tails: set[str] = set()
        for t in self.terms:
            node, k, n = self.root, edits(len(t)), len(t)
            for c in ["", *t]:
                node = node.next.setdefault(c, Node()) if c else node
                node.least, node.longest = min(node.least, n), max(node.longest, n)
            node.term = t
            cuts = [n * i // (k + 1) for i in range(k + 2)]
            if k:
                tails.add(t[cuts[-2]:])
                parts.update((at + d, t[at:to]) for at, to in zip(cuts[:-2], cuts[1:]) for d in range(-k, k + 1) if at + d == at == 0 or at and at + d >= 0)
        self._tails = [(n, frozenset(x for x in tails if len(x) == n)) for n in sorted({len(x) for x in tails})]
        self._parts = [(at, at + n, frozenset(x for a, x in parts if a == at and len(x) == n)) for at, n in sorted({(a, len(x)) for a, x in parts})]

    def kind(self, word: str) -> int:
        if word in self.terms:
            return EXACT
        if len(word) < 4 or not (any(word[-n:] in x for n, x in self._tails) or any(word[a:b] in x for a, b, x in self._parts)):
            return NONE
        return NEAR if self.near(word) else NONE

    def near(self, word: str) -> bool:
        """Whether a term is within its allowed edits.

        The automaton's states after no, one and two edits are bit sets over the
        places of the word, moved on along the edges of the trie.
        """
        n, at = len(word), {}
        for i, c in enumerate(word):
            at[c] = at.get(c, 0) | 1 << i
        done = 1 << n
        todo = [(self.root, 1, 3, 7)]
        while todo:
            node, r0, r1, r2 = todo.pop()
            for c, child in node.next.items():
                if n > child.longest + 2 or n < child.least - 2:
                    continue
                m = at.get(c, 0)
                s0 = (r0 & m) << 1
                s1 = (r1 & m) << 1 | r0 | r0 << 1 | s0 << 1
                s2 = (r2 & m) << 1 | r1 | r1 << 1 | s1 << 1
                if child.term is not None and (s0, s1, s2)[edits(len(child.term))] & done:
                    return True
                if child.next and (s1 if child.longest < 12 else s2) & (2 * done - 1):
                    todo.append((child, s0, s1, s2))
        return False


class Scanner:
    """Hits of a text; the kinds of words are memoised in a table of bounded size."""

    def __init__(self, trie: Trie, excluded: frozenset = frozenset(), limit: int = 500_000):
        self.trie, self.excluded, self.limit, self.known = trie, excluded, limit, {}

    def __call__(self, text: str | None) -> list[tuple[str, int, bool, bool]]:
        """(word, kind, quoted, aimed) of each hit."""
        words = _WORD.findall((text or "").lower())
        new = set(words).difference(self.known)
        if len(self.known) > self.limit:
            self.known.clear()
            new = set(words)
        for w in new:
            self.known[w] = NONE if w in self.excluded else self.trie.kind(w)
        at = [i for i, k in enumerate(map(self.known.__getitem__, words)) if k]
        if not at:
            return []
        marks = [i for i, w in enumerate(words) if w in QUOTES] if not QUOTES.isdisjoint(words) else []
        out = []
        for i in at:
            near = words[max(0, i - WINDOW):i + WINDOW + 1]
            opened = any(i - WINDOW <= m < i for m in marks) and any(i < m <= i + WINDOW for m in marks)
            told = not REPORTING.isdisjoint(words[max(0, i - 3):i])
            out.append((words[i], self.known[words[i]], opened or told, not ADDRESS.isdisjoint(near)))
        return out


def counts(hits) -> np.ndarray:
    """log(1 + n) of plain exact, plain near, quoted and aimed hits, and whether any is plain and exact."""
    exact = sum(k == EXACT and not q for _, k, q, _ in hits)
    near = sum(k == NEAR and not q for _, k, q, _ in hits)
    return np.array([np.log1p(exact), np.log1p(near), np.log1p(sum(q for *_, q, _ in hits)), np.log1p(sum(a and not q for *_, q, a in hits)), float(exact > 0)])


@dataclass
class Model:
    terms: frozenset = frozenset()
    excluded: frozenset = frozenset()
    weights: np.ndarray = field(default_factory=lambda: np.zeros(6))

    def score(self, hits) -> float:
        z = float(self.weights[0] + self.weights[1:] @ counts(hits))
        return float(1 / (1 + np.exp(-np.clip(z, -40, 40))))


def logistic(x: np.ndarray, y: np.ndarray, ridge: float = 0.05, steps: int = 50) -> np.ndarray:
    """Weights, intercept first, by Newton steps."""
    x = np.hstack([np.ones((len(x), 1)), x])
    w, pull = np.zeros(x.shape[1]), np.full(x.shape[1], ridge)
    pull[0] = 1e-6
    for _ in range(steps):
        p = 1 / (1 + np.exp(-np.clip(x @ w, -30, 30)))
        g = x.T @ (p - y) + pull * w
        step = np.linalg.solve((x * (p * (1 - p))[:, None]).T @ x + np.diag(pull + 1e-9), g)
        w -= np.clip(step, -5, 5)
        if np.abs(step).max() < 1e-8:
            break
    return w


def held_out(doc_id):
    return F.coalesce(F.crc32(doc_id.cast("string").cast("binary")) % 5 == 0, F.lit(False))


def training_rows(docs: DataFrame, labels: DataFrame, max_train: int) -> DataFrame:
    """(text, toxic) of at most ``max_train`` labelled rows that are not held out."""
    own = labels.select(F.col("doc_id").cast("long").alias("doc_id"), F.col("toxic").cast("int").alias("toxic")).where("toxic is not null and doc_id is not null").where(~held_out(F.col("doc_id")))
    some = own.groupBy("doc_id").agg(F.max("toxic").alias("toxic")).orderBy(F.xxhash64("doc_id"), "doc_id").limit(max_train)
    return docs.select(F.col("doc_id").cast("long").alias("doc_id"), F.col("text").cast("string").alias("text")).join(F.broadcast(some), "doc_id").select("text", "toxic")


def _contexts(rows: DataFrame) -> DataFrame:
    """(word, toxic, n): different contexts of each word, by class."""
    def run(batches):
        for b in batches:
            seen = set()
            for text, toxic in zip(b.column(0).to_pylist(), b.column(1).to_pylist()):
                w = ["", *(x for x in _WORD.findall((text or "").lower()) if x not in QUOTES), ""]
                seen.update((x, xxhash.xxh64_intdigest(f"{p} {n}") >> 1, toxic) for p, x, n in zip(w, w[1:], w[2:]))
            if seen:
                x, c, t = zip(*seen)
                yield pa.RecordBatch.from_arrays([pa.array(x), pa.array(c, pa.int64()), pa.array(t, pa.int32())], names=["word", "context", "toxic"])

    found = rows.mapInArrow(run, "word string, context long, toxic int").distinct()
    return found.groupBy("word").agg(F.sum("toxic").alias("toxic"), F.sum(1 - F.col("toxic")).alias("clean"))


def _support(seen: DataFrame, least: int, most: int = 12) -> int:
    """The fewest toxic contexts at which chance alone would make less than half a term."""
    both = F.col("toxic") + F.col("clean")
    sums = seen.agg(F.sum("toxic").alias("t"), F.sum(both).alias("all"), *(F.count_if(both >= n).alias(f"n{n}") for n in range(least, most))).first()
    share = (sums["t"] or 0) / max(1, sums["all"] or 0)
    return next((n for n in range(least, most) if sums[f"n{n}"] * share**n < 0.5), most)


def fit(docs: DataFrame, labels: DataFrame, max_train: int = 12_000, least: int = 3, ratio: float = 20.0) -> Model:
    from relmine.llm.common import saved

    rows = saved(training_rows(docs, labels, max_train), "training")
    by = {int(r["toxic"] > 0): r["n"] for r in rows.groupBy((F.col("toxic") > 0).cast("int").alias("toxic")).agg(F.count("*").alias("n")).collect()}
    toxic, clean = by.get(1, 0), by.get(0, 0)
    if not toxic or not clean:
        w = np.zeros(6)
        w[0] = np.log((toxic + 0.5) / (clean + 0.5))
        return Model(weights=w)
    rate = lambda n, of: (F.col(n) + 0.5) / F.lit(of + 1.0)
    seen = saved(_contexts(rows).where(F.col("toxic") + F.col("clean") >= least), "contexts")
    terms = seen.where((F.col("toxic") >= _support(seen, least)) & (F.length("word") >= 3) & (rate("toxic", toxic) >= ratio * rate("clean", clean)))
    lexicon = frozenset(r["word"] for r in terms.collect())  # words of the bounded sample
    trie = Trie(lexicon)

    def run(batches):
        scan = Scanner(trie)
        for b in batches:
            hits = [scan(t) for t in b.column(0).to_pylist()]
            yield pa.RecordBatch.from_arrays([b.column(1), pa.array([[{"w": w, "k": k, "q": q, "a": a} for w, k, q, a in h] for h in hits], pa.list_(pa.struct([("w", pa.string()), ("k", pa.int32()), ("q", pa.bool_()), ("a", pa.bool_())])))], names=["toxic", "hits"])

    got = [(int(r["toxic"] > 0), [(h["w"], h["k"], h["q"], h["a"]) for h in r["hits"]]) for r in rows.mapInArrow(run, "toxic int, hits array<struct<w:string,k:int,q:boolean,a:boolean>>").collect()]
    excluded = frozenset(w for y, hits in got if not y for w, k, *_ in hits if k == NEAR)
    x = np.array([counts([h for h in hits if h[0] not in excluded]) for _, hits in got])
    w = logistic(x, np.array([y for y, _ in got], float))
    if not x[:, 1].any():  # no misspelled term in the sample: one weighs as one whole term
        w[2] = w[1] + w[5] / np.log(2)
    return Model(lexicon, excluded, w)


def score(docs: DataFrame, model: Model) -> DataFrame:
    """(doc_id, held_out, score, predicted), a row for each row of ``docs``."""
    trie = Trie(model.terms)

    def run(batches):
        scan = Scanner(trie, model.excluded)
        for b in batches:
            s = [model.score(scan(t)) for t in b.column(2).to_pylist()]
            yield pa.RecordBatch.from_arrays([b.column(0), b.column(1), pa.array(s, pa.float64()), pa.array([int(v >= 0.5) for v in s], pa.int32())], names=["doc_id", "held_out", "score", "predicted"])

    ids = F.col("doc_id").cast("long")
    return docs.select(ids.alias("doc_id"), held_out(ids).alias("held_out"), F.col("text").cast("string").alias("text")).mapInArrow(
        run, "doc_id long, held_out boolean, score double, predicted int")


def toxicity(docs: DataFrame, labels: DataFrame, max_train: int = 12_000) -> DataFrame:
    return score(docs, fit(docs, labels, max_train))
