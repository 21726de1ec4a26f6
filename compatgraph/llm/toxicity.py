"""Toxicity scores: Levenshtein automata intersected with a lexicon trie, and context windows around the hits.

Fitting.  A bounded sample of labelled training rows (``TRAIN_ROWS``, the least hashes of doc_id) gives the lexicon: words and
word stems that toxic rows have and others lack, by log-odds of all their forms, shortest form first; only the sample bounds it.  The terms form a trie; the automaton
of all strings within each term's edit budget is intersected with it and made deterministic as tokens are read, so
a token is matched in one pass and most are dropped after a few characters.  Features of a document count exact, misspelled
and distinct hits, their weights, and what stands in a window around each: quotation marks and reporting verbs
(quotation) or second-person words (abuse).  A logistic model on the sample turns them into a score.

Scoring reads every whole text; labels, lang, source and doc_id are no inputs.  Null and empty texts have no hits and get
the score of a text without hits.  Without labels of both kinds every score is 0.  Repeated label rows of a doc_id
count once (toxic if one says so); null labels are left out.  Repeated rows get equal scores, an empty table gives an empty
result, very long texts and tokens are read whole, and other columns, whatever their names, are not read.
"""

from __future__ import annotations

import math
import re
from collections import Counter

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from .common import col, map_text, materialise, texts

TRAIN_ROWS, CACHE_TOKENS, CACHE_CHARS = 20_000, 300_000, 64
STEMS = range(4, 8)
WINDOW = 8
TOKEN = re.compile(r"[\w@$]+")
_PLAIN = str.maketrans("013457@$", "oieastas")
# Words around a hit.
YOU = frozenset("you your youre ur u du dich dir dein ihr euch tu te toi ton vous votre tú ti tu usted vosotros".split())
SAID = frozenset("said says wrote writes called quoted quote asked reported sagte schrieb nannte dit écrit appelé dijo escribió llamó".split())
QUOTES = frozenset("\"'“”„«»‘’")


class Lexicon:
    """Trie of terms with the edits each allows; ``match`` runs the lazily built automaton."""

    def __init__(self, terms: list[tuple[str, bool, float]]):
        self.terms = terms  # (text, whole word, weight)
        self.child: list[dict[str, int]] = [{}]
        self.end: list[int] = [-1]
        self.most: list[int] = [0]
        for k, (text, whole, _) in enumerate(terms):
            edits, node = budget(text, whole), 0
            for c in text:
                self.most[node] = max(self.most[node], edits)
                if c not in self.child[node]:
                    self.child[node][c] = len(self.child)
                    self.child.append({}), self.end.append(-1), self.most.append(0)
                node = self.child[node][c]
            self.most[node] = max(self.most[node], edits)
            self.end[node] = k
        self.states: dict[tuple, int] = {}
        self.sets: list[dict[int, int]] = []
        self.step: list[dict[str, int]] = []
        self.word: list[tuple[int, int] | None] = []
        self.stem: list[tuple[int, int] | None] = []
        self.start = self.state({0: 0})
        self.seen: dict[str, tuple[int, int] | None] = {}

    def state(self, reached: dict[int, int]) -> int:
        """Number of a set of (node, edits), with the nodes that left-out characters reach."""
        todo = list(reached.items())
        while todo:
            node, e = todo.pop()
            for n in self.child[node].values():
                if e + 1 <= self.most[n] and reached.get(n, 9) > e + 1:
                    reached[n] = e + 1
                    todo.append((n, e + 1))
        key = tuple(sorted(reached.items()))
        if key not in self.states:
            self.states[key] = len(self.sets)
            self.sets.append(reached), self.step.append({})
            best: list = [None, None]
            for n, e in key:
                if (k := self.end[n]) >= 0 and e <= budget(*self.terms[k][:2]):
                    whole = self.terms[k][1]
                    if best[whole] is None or e < best[whole][1]:
                        best[whole] = (k, e)
            self.stem.append(best[0]), self.word.append(best[1])
        return self.states[key]

    def follow(self, s: int, c: str) -> int:
        reached: dict[int, int] = {}
        for node, e in self.sets[s].items():
            if e + 1 <= self.most[node] and reached.get(node, 9) > e + 1:
                reached[node] = e + 1
            for ch, n in self.child[node].items():
                cost = e + (ch != c)
                if cost <= self.most[n] and reached.get(n, 9) > cost:
                    reached[n] = cost
        self.step[s][c] = t = self.state(reached)
        return t

    def match(self, token: str) -> tuple[int, int] | None:
        """Term and edits of a token: a whole word within its budget, else a stem it begins with."""
        s, stem = self.start, None
        for c in token:
            t = self.step[s].get(c)
            s = self.follow(s, c) if t is None else t
            if self.stem[s] is not None and (stem is None or self.stem[s][1] < stem[1]):
                stem = self.stem[s]
            if not self.sets[s]:
                return stem
        word = self.word[s]
        return word if word is not None and (stem is None or word[1] <= stem[1]) else stem

    def find(self, token: str) -> tuple[int, int] | None:
        hit = self.match(token)
        if hit is None and (plain := token.translate(_PLAIN)) != token and not token.isdigit():
            hit = self.match(plain)
            hit = hit and (hit[0], max(1, hit[1]))
        return hit

    def hits(self, tokens: list[str]) -> dict[str, tuple[int, int]]:
        """Hits among the distinct tokens; a bounded cache keeps what was found."""
        new = set(tokens)
        if len(self.seen) + len(new) > CACHE_TOKENS:
            self.seen = {}
        out = {}
        for t in new:
            if t in self.seen:
                h = self.seen[t]
            else:
                h = self.find(t)
                if len(t) <= CACHE_CHARS:  # longer ones are looked up each time
                    self.seen[t] = h
            if h is not None:
                out[t] = h
        return out


def budget(text: str, whole: bool) -> int:
    return (0 if len(text) < 5 else 1 if len(text) < 9 else 2) if whole else int(len(text) >= 7)


def features(text: str, lexicon: Lexicon) -> list[float]:
    """Counts, weights and context of the hits of a text; all 0 without hits."""
    lowered = text.lower()
    hits = lexicon.hits(TOKEN.findall(lowered))
    if not hits:
        return [0.0] * 11
    tokens = list(TOKEN.finditer(lowered))
    words = [m[0] for m in tokens]
    exact = fuzzy = quoted = said = you = 0
    weights, terms = [], set()
    for i, w in enumerate(words):
        if w not in hits:
            continue
        k, e = hits[w]
        exact, fuzzy = exact + (e == 0), fuzzy + (e > 0)
        terms.add(k)
        weights.append(lexicon.terms[k][2] * 0.5**e)
        a, b = max(0, i - WINDOW), min(len(words), i + WINDOW + 1)
        before, after = lowered[tokens[a].start() : tokens[i].start()], lowered[tokens[i].end() : tokens[b - 1].end()]
        inside = any(c in QUOTES for c in before) and any(c in QUOTES for c in after)
        near = words[a:b]
        quoted, said, you = quoted + inside, said + any(x in SAID for x in near), you + any(x in YOU for x in near)
    n = exact + fuzzy
    return [1.0, math.log1p(exact), math.log1p(fuzzy), math.log1p(len(terms)), max(weights), math.log1p(sum(weights)), math.log1p(quoted), math.log1p(n - quoted), math.log1p(said), math.log1p(you), math.log1p(100 * n / len(words))]


def fit_logistic(x: np.ndarray, y: np.ndarray, ridge: float = 1.0, rounds: int = 30) -> dict:
    """Newton steps on standardised features."""
    mean, std = x.mean(0), x.std(0) + 1e-9
    z = np.column_stack([(x - mean) / std, np.ones(len(x))])
    w, penalty = np.zeros(z.shape[1]), np.diag([ridge] * x.shape[1] + [1e-6])
    for _ in range(rounds):
        p = 1 / (1 + np.exp(-np.clip(z @ w, -30, 30)))
        step = np.linalg.solve((z * (p * (1 - p) + 1e-9)[:, None]).T @ z + penalty, z.T @ (y - p) - penalty @ w)
        w += step
        if np.abs(step).max() < 1e-6:
            break
    return {"mean": mean, "std": std, "w": w}


def probability(model: dict, x: np.ndarray) -> np.ndarray:
    z = (x - model["mean"]) / model["std"]
    return 1 / (1 + np.exp(-np.clip(z @ model["w"][:-1] + model["w"][-1], -30, 30)))


def forms(text: str) -> set[tuple[str, bool]]:
    """Whole words and stems of a text."""
    out: set[tuple[str, bool]] = set()
    for w in set(TOKEN.findall(text.lower())):
        if not w.isdigit():
            if len(w) >= 3:
                out.add((w, True))
            out.update((w[:k], False) for k in STEMS if len(w) >= k)
    return out


def choose_terms(scored: list[tuple[str, bool, int, float]]) -> list[tuple[str, bool, float]]:
    """Of forms (text, whole, toxic rows, weight) the terms; a longer form goes where a chosen shorter one covers it."""
    chosen: dict[str, tuple[str, bool, float, int]] = {}
    most: dict[str, int] = {}  # by beginning, of the words in most rows
    for text, whole, a, _ in scored:
        for k in STEMS if whole else ():
            most[text[:k]] = max(a, most.get(text[:k], 0))
    for text, whole, a, weight in sorted(scored, key=lambda s: (len(s[0]), s[1], s[0])):
        if not whole and most.get(text, 0) >= 0.98 * a:
            continue  # a stem of one word only: the word itself can also be met misspelled
        if text not in chosen and not any(text[:k] in chosen and not chosen[text[:k]][1] for k in STEMS):
            chosen[text] = (text, whole, weight, a)
    return [c[:3] for c in sorted(chosen.values(), key=lambda c: (-c[3], c[0]))]


def fit(docs: DataFrame, labels: DataFrame, *, train_rows: int = TRAIN_ROWS) -> tuple[list, dict] | None:
    """Lexicon and model from a bounded sample of training labels; None without both kinds of label."""
    known = labels.select(F.col("`doc_id`"), (F.col("`toxic`") == 1).cast("int").alias("toxic")).filter("doc_id is not null and toxic is not null").filter(~held_out("doc_id"))
    sample = known.groupBy("doc_id").agg(F.max("toxic").alias("toxic")).orderBy(F.xxhash64("doc_id"), "doc_id").limit(train_rows)
    sample = materialise(sample, "toxic-sample")  # at most train_rows ids: broadcast
    rows = docs.select(F.col("`doc_id`"), F.col("`text`")).join(F.broadcast(sample), "doc_id").select("text", "toxic")
    rows = materialise(rows, "toxic-texts")
    by_kind = {r.toxic: r["count"] for r in rows.groupBy("toxic").count().collect()}
    n_toxic, n_clean = by_kind.get(1, 0), by_kind.get(0, 0)
    if not n_toxic or not n_clean:
        return None

    def counted(batch: pa.RecordBatch) -> pa.RecordBatch:
        both: tuple[Counter, Counter] = Counter(), Counter()
        for t, toxic in zip(texts(batch), col(batch, "toxic").to_pylist(), strict=True):
            both[toxic].update(forms(t))
        own = [(f, w, both[1][f, w], both[0][f, w]) for f, w in both[0].keys() | both[1].keys()]
        return pa.RecordBatch.from_arrays([pa.array(x, t) for x, t in zip(zip(*own, strict=True) if own else ([],) * 4, (pa.string(), pa.bool_(), pa.int64(), pa.int64()), strict=True)], names=["form", "whole", "a", "b"])

    counts = map_text(rows, counted, "form string, whole boolean, a long, b long").groupBy("form", "whole").agg(F.sum("a").alias("a"), F.sum("b").alias("b"))
    odds = lambda n, of: F.log((F.col(n) + 0.5) / (F.lit(of) - F.col(n) + 0.5))
    # precise at the sample's base rate, and not by chance; what passes is bounded by the sample's texts
    scored = counts.withColumn("weight", odds("a", n_toxic) - odds("b", n_clean)).filter((F.col("a") >= 3) & (F.col("a") >= 4 * F.col("b")) & (F.col("weight") >= 3) & (F.col("a") > 0.95 * (F.col("a") + F.col("b") * (n_toxic / n_clean))))
    terms = choose_terms([(r.form, r.whole, r.a, r.weight) for r in scored.select("form", "whole", "a", "weight").collect()])
    made: list[Lexicon] = []

    def measured(batch: pa.RecordBatch) -> pa.RecordBatch:
        if not made:
            made.append(Lexicon(terms))
        x = [features(t, made[0]) for t in texts(batch)]
        return pa.RecordBatch.from_arrays([pa.array(x, pa.list_(pa.float64())), col(batch, "toxic")], names=["x", "toxic"])

    # at most train_rows rows of 11 numbers
    found = sorted((r.toxic, r.x) for r in map_text(rows, measured, "x array<double>, toxic int").collect())
    return terms, fit_logistic(np.array([x for _, x in found]), np.array([t for t, _ in found], float))


def held_out(name: str):
    return F.crc32(F.coalesce(F.col(name).cast("string"), F.lit("")).cast("binary")) % 5 == 0


def score(docs: DataFrame, fitted: tuple[list, dict] | None) -> DataFrame:
    """doc_id, held_out, score, predicted of every document."""
    made: list[Lexicon] = []

    def run(batch: pa.RecordBatch) -> pa.RecordBatch:
        if fitted and not made:
            made.append(Lexicon(fitted[0]))
        p = probability(fitted[1], np.array([features(t, made[0]) for t in texts(batch)])) if fitted else np.zeros(batch.num_rows)
        return pa.RecordBatch.from_arrays([col(batch, "doc_id"), col(batch, "held_out"), pa.array(p), pa.array((p >= 0.5).astype(np.int32))], names=["doc_id", "held_out", "score", "predicted"])

    rows = docs.select(F.col("`doc_id`"), held_out("`doc_id`").alias("held_out"), F.col("`text`"))
    return map_text(rows, run, "doc_id long, held_out boolean, score double, predicted int")
