"""Toxicity: a lexicon learned from labels, a Levenshtein automaton over its trie, and scores of what stands around.

Terms are words or beginnings of words (families of one stem) that labelled toxic documents hold far more often than others.
Words of a text are run through the trie with a row of edit distances as the automaton's state, so that misspelled terms are
caught; hits between quotation marks, or alone among many words, weigh otherwise than dense unquoted ones. A logistic model
of these counts gives the score.
"""

from __future__ import annotations

import re
from collections.abc import Iterator
from dataclasses import dataclass, field

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from seqstat.llm.shared import ascii_words, fold, sample_rows, stage
from seqstat.llm.simhash import shingle_hashes

WORD = re.compile(r"[^\W_]+")
QUOTES = re.compile("[\"“”„«»]")
STEMS = range(4, 9)
FEATURES = 9


def terms_of(text: str) -> set[str]:
    """Distinct words, and beginnings of 4 to 8 letters marked with a star."""
    words = set(WORD.findall(text.lower()))
    return words | {w[:n] + "*" for w in words for n in STEMS if len(w) >= n}


class Automaton:
    """The Levenshtein automaton for a bound, the same for all words: a state holds the distances, up to the bound, at the places of a word
    within the bound of the depth; which of the 2 * bound + 1 characters there equal the next one of a term leads to the next state.
    States and steps are made once."""

    def __init__(self, edits: int):
        self.edits, self.over = edits, edits + 1
        self.start = tuple(max(0, j) if j >= 0 else self.over for j in range(-edits, edits + 1))
        self.steps: dict[tuple, tuple[int, ...] | None] = {}

    def step(self, state: tuple[int, ...], equal: tuple[bool, ...]) -> tuple[int, ...] | None:
        """The next state, or None where no place is within the bound; ``equal`` is for the places after the step."""
        key = state, equal
        if key not in self.steps:
            out: list[int] = []
            for i, same in enumerate(equal):
                dropped = state[i + 1] + 1 if i + 1 < len(state) else self.over
                added = out[i - 1] + 1 if i else self.over
                out.append(min(self.over, dropped, added, state[i] + (not same)))
            self.steps[key] = tuple(out) if min(out) <= self.edits else None
        return self.steps[key]


class Lexicon:
    """Terms in a trie; a term that ends in a star is met by every word that begins with it."""

    def __init__(self, terms: dict[str, float], fuzzy_from: int = 5, edits: int = 1):
        self.terms, self.edits, self.fuzzy_from = terms, edits, fuzzy_from
        self.automaton = Automaton(edits)
        self.words = {t: w for t, w in terms.items() if not t.endswith("*")}
        self.stems = {t[:-1]: w for t, w in terms.items() if t.endswith("*")}
        self.stem_lengths = sorted({len(t) for t in self.stems})
        self.trie: dict = {}
        self.heads, self.tails, self.middles = set(), set(), set()
        for t, w in terms.items():
            bare = t.rstrip("*")
            if len(bare) < (fuzzy_from if t == bare else fuzzy_from + 1):
                continue
            node = self.trie
            for c in bare:
                node = node.setdefault(c, {})
            node.setdefault("ends", []).append((t.endswith("*"), w))
            half = len(bare) // 2  # one edit leaves one half as it is
            self.heads.add(bare[:half])
            if t == bare:
                self.tails.add(bare[half:])
            else:  # the untouched second half of a stem stands at its place or one beside it
                self.middles.update((at, bare[half:]) for at in (half - 1, half, half + 1))
        escaped = lambda parts: "|".join(sorted(map(re.escape, parts))) or "(?!)"
        middles = "|".join(f".{{{at}}}{re.escape(m)}" for at, m in sorted(self.middles)) or "(?!)"
        self.half = re.compile(f"(?:{escaped(self.heads)}|{middles}|.*(?:{escaped(self.tails)})\\Z)", re.DOTALL)

    def exact(self, word: str) -> float:
        best = self.words.get(word, 0.0)
        for n in self.stem_lengths:
            if n > len(word):
                break
            best = max(best, self.stems.get(word[:n], 0.0))
        return best

    def possible(self, word: str) -> bool:
        """Whether a half of some term stands where one edit leaves it: at the beginning, the end, or a stem's middle. More edits
        may touch both halves, so then every word goes through the trie."""
        return self.edits != 1 or self.half.match(word) is not None

    def fuzzy(self, word: str) -> float:
        """The largest weight of a term within ``edits`` of the word (of its beginning, for stems)."""
        k, n = self.edits, len(word)
        if n < self.fuzzy_from - k or not self.possible(word):
            return 0.0
        best, stack = 0.0, [(self.trie, 0, self.automaton.start)]
        padded = "\0" * (k + 1) + word + "\0" * (2 * k + 2)
        while stack:
            node, depth, state = stack.pop()
            at_end = state[n - depth + k] if -k <= n - depth <= k else k + 1
            nearest = min(x for j, x in enumerate(state, depth - k) if j <= n) if depth - k <= n else k + 1
            for stem, weight in node.get("ends", ()):
                if at_end <= k or stem and nearest <= k:
                    best = max(best, weight)
            window = padded[depth + 1 : depth + 2 * k + 2]  # the characters before the places depth + 1 - k ... depth + 1 + k
            for c, child in node.items():
                if c != "ends" and (after := self.automaton.step(state, tuple(x == c for x in window))):
                    stack.append((child, depth + 1, after))
        return best


class Hits(dict):
    """Word → 0 (none), weight (a term) or minus weight (a misspelled one); emptied at ``most`` words."""

    def __init__(self, lexicon: Lexicon, most: int = 400_000):
        self.lexicon, self.most = lexicon, most

    def __missing__(self, word: str) -> float:
        found = self.lexicon.exact(word) or -self.lexicon.fuzzy(word)
        if len(self) >= self.most:
            self.clear()
        self[word] = found
        return found


def features(text: str, hits: Hits, window: int = 8) -> np.ndarray:
    """Counts of hits by kind and surroundings; zeros where there is none."""
    lowered = text.lower()
    words = WORD.findall(lowered)
    found = np.fromiter(map(hits.__getitem__, words), np.float64, len(words))
    at = np.flatnonzero(found)
    out = np.zeros(FEATURES)
    if not len(at):
        return out
    marks = np.array([m.start() for m in QUOTES.finditer(lowered)])
    quoted = 0
    if len(marks) > 1:
        places = np.array([m.start() for m in WORD.finditer(lowered)])[at]
        before = np.searchsorted(marks, places)
        near = (before > 0) & (before < len(marks))
        spans = marks[np.minimum(before, len(marks) - 1)] - marks[np.maximum(before - 1, 0)]
        quoted = int((near & (before % 2 == 1) & (spans < 400)).sum())
    dense = int((np.diff(at) <= window).sum()) if len(at) > 1 else 0
    weight = np.abs(found[at])
    plain = int((found[at] > 0).sum())
    out[:] = (1, np.log1p(plain), np.log1p(len(at) - plain), np.log1p(quoted), quoted / len(at), np.log1p(dense), min(1.0, 20 * len(at) / len(words)), weight.max(), min(10.0, weight.sum()) / 3)
    return out


@dataclass
class Model:
    terms: dict[str, float] = field(default_factory=dict)
    weights: np.ndarray = field(default_factory=lambda: np.zeros(FEATURES))
    bias: float = -3.0

    def score(self, x: np.ndarray) -> np.ndarray:
        return 1 / (1 + np.exp(-np.clip(x @ self.weights + self.bias, -30, 30)))


def surprise(p: int, n: int, positives: int, negatives: int) -> float:
    """Twice the log-likelihood ratio of a term's share of toxic documents against the share of all (the G statistic)."""
    rate, own = positives / (positives + negatives), p / (p + n)
    return 2 * (p * np.log(own / rate) + (n * np.log((1 - own) / (1 - rate)) if n else 0.0))


def choose_terms(counts: list[tuple[str, int, int]], positives: int, negatives: int, most: int = 2000, least_odds: float = 2.0, least_surprise: float = 28.0) -> dict[str, float]:
    """Terms by smoothed log odds that chance would hardly give; what begins with a stem that is a term goes, and a stem gives way to
    the longest term that holds in nine tenths of its documents."""
    counts = [x for x in counts if x[1] and surprise(*x[1:], positives, negatives) >= least_surprise]
    odds = {t: np.log((p + 0.5) / (positives + 1)) - np.log((n + 0.5) / (negatives + 1)) for t, p, n in counts}
    seen = {t: (p, n) for t, p, n in counts}
    pure = sorted((t for t, p, n in counts if odds[t] >= least_odds and p / (p + n) >= 0.5), key=lambda t: (len(t.rstrip("*")), not t.endswith("*"), t))
    kept: dict[str, float] = {}
    grown: set[str] = set()  # stems that a longer term stands for
    for t in pure:
        bare = t.rstrip("*")
        if any(bare[:k] + "*" in kept or bare[:k] + "*" in grown for k in STEMS if k <= len(bare)):
            continue
        best = t
        if t.endswith("*"):  # the longest word or stem that loses hardly any of these documents, the word first
            same = [x for x in pure if x.startswith(bare) and seen[x][0] >= 0.9 * seen[t][0]]
            best = max(same, key=lambda x: (len(x.rstrip("*")), not x.endswith("*")), default=t)
            grown.add(t)
        kept[best] = float(odds[best])
    ranked = sorted(kept, key=lambda t: (-odds[t] * np.sqrt(min(seen[t][0], 200)), t))[:most]
    return {t: kept[t] for t in ranked}


def fit_logistic(x: np.ndarray, y: np.ndarray, ridge: float = 0.05, turns: int = 30) -> tuple[np.ndarray, float]:
    """Newton's method with a ridge."""
    z = np.hstack([x, np.ones((len(x), 1))])
    w = np.zeros(z.shape[1])
    for _ in range(turns):
        p = 1 / (1 + np.exp(-np.clip(z @ w, -30, 30)))
        h = (z * (p * (1 - p))[:, None]).T @ z + ridge * np.eye(len(w))
        step = np.linalg.solve(h, z.T @ (p - y) + ridge * w)
        w -= step
        if np.abs(step).max() < 1e-6:
            break
    return w[:-1], float(w[-1])


def train(docs: DataFrame, labels: DataFrame, held_out: int = 1, folds: int = 3, positives: int = 2000, negatives: int = 4000, least: int = 4, seed: int = 23) -> Model:
    """Fit on at most so many labelled rows of each class outside the held-out fold, chosen by a hash of the id.

    Documents that share their least five-word hash count once. Terms are counted where the documents lie; the driver gets the counts of at most 20,000 terms and a feature row of each of
    these documents. The logistic model is fitted on a third of the sample, with terms that the other two thirds gave.
    """
    usable = labels.where((fold(F.col("doc_id"), folds) != held_out) & F.col("toxic").isin(0, 1) & F.col("doc_id").isNotNull()).select("doc_id", "toxic").distinct()
    drawn = sample_rows(usable.where("toxic = 1"), positives, seed) + sample_rows(usable.where("toxic = 0"), negatives, seed)
    ids = docs.sparkSession.createDataFrame(drawn, "doc_id long, toxic int")  # at most positives + negatives rows
    chosen = docs.select(F.col("doc_id").cast("long").alias("doc_id"), F.col("text").cast("string").alias("text"))

    def sign(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in batches:
            least = [int(min(shingle_hashes(ascii_words(x.as_py()), 5).view(np.int64).tolist(), default=0)) for x in batch.column(1)]
            yield pa.RecordBatch.from_arrays([*batch.columns, pa.array(least, pa.int64())], ["toxic", "text", "sign"])

    signed = chosen.join(F.broadcast(ids), "doc_id").where("text is not null").select("toxic", "text").mapInArrow(sign, "toxic int, text string, sign long")
    single = signed.dropDuplicates(["sign", "toxic"])  # copies and most near copies count once: else their rare words look telling
    rows = stage(single.withColumn("part", F.pmod(F.xxhash64(F.lit(seed + 1), "sign"), F.lit(3)).cast("int")), "labelled")
    totals = {(r["toxic"], r["part"]): r["count"] for r in rows.groupBy("toxic", "part").count().collect()}
    of = lambda toxic, parts: sum(totals.get((toxic, p), 0) for p in parts)
    if not of(1, (0, 1, 2)) or not of(0, (0, 1, 2)):
        return Model()

    def count(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in batches:
            sums: dict[str, list[int]] = {}
            for toxic, part, text in zip(batch.column(0).to_pylist(), batch.column(1).to_pylist(), batch.column(2), strict=True):
                at = 1 - toxic  # p, n of the first two thirds; pa, na of all
                for term in terms_of(text.as_py() or ""):
                    found = sums.setdefault(term, [0, 0, 0, 0])
                    found[2 + at] += 1
                    found[at] += part != 2
            columns = [pa.array([v[i] for v in sums.values()], pa.int64()) for i in range(4)]
            yield pa.RecordBatch.from_arrays([pa.array(list(sums), pa.string()), *columns], ["term", "p", "n", "pa", "na"])

    listed = rows.select("toxic", "part", "text").mapInArrow(count, "term string, p long, n long, pa long, na long")
    counted = listed.groupBy("term").agg(*[F.sum(c).alias(c) for c in ("p", "n", "pa", "na")])
    strong = counted.where((F.col("pa") >= least) & (F.col("pa") >= F.col("na"))).orderBy(F.desc(F.col("pa") - F.col("na")), "term").limit(20_000).collect()
    first = choose_terms([(r["term"], r["p"], r["n"]) for r in strong], of(1, (0, 1)), of(0, (0, 1)))
    final = choose_terms([(r["term"], r["pa"], r["na"]) for r in strong], of(1, (0, 1, 2)), of(0, (0, 1, 2)))

    def measure(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        hits = Hits(Lexicon(first))
        for batch in batches:
            x = [features(t.as_py() or "", hits).tolist() for t in batch.column(1)]
            yield pa.RecordBatch.from_arrays([batch.column(0), pa.array(x, pa.list_(pa.float64()))], ["toxic", "x"])

    table = sorted(rows.where("part = 2").select("toxic", "text").mapInArrow(measure, "toxic int, x array<double>").collect())  # of the bounded sample
    x, y = np.array([r["x"] for r in table]).reshape(-1, FEATURES), np.array([r["toxic"] for r in table], float)
    if not y.any() or y.all():
        return Model(final, np.r_[np.full(1, 4.0), np.zeros(FEATURES - 1)], -3.0)
    weights, bias = fit_logistic(x, y)
    return Model(final, weights, bias)


def score(docs: DataFrame, labels: DataFrame, held_out: int = 1, folds: int = 3, threshold: float = 0.7, **options) -> DataFrame:
    """(doc_id, held_out, score, predicted, hits) for every row; every whole text is read.

    Null and empty texts, like all texts without a hit, get the model's base rate; repeated rows agree; without labels of both kinds
    all scores are low and equal; an empty table gives no rows; other columns are ignored.
    """
    model = train(docs, labels, held_out, folds, **options)
    sent = docs.sparkSession.sparkContext.broadcast(model)

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        hits = Hits(Lexicon(sent.value.terms))
        for batch in batches:
            x = np.array([features(t.as_py() or "", hits) for t in batch.column(2)]).reshape(-1, FEATURES)
            p = sent.value.score(x)
            yield pa.RecordBatch.from_arrays([batch.column(0), batch.column(1), pa.array(p), pa.array((p >= threshold).astype(np.int32)), pa.array(x[:, 0] > 0)], ["doc_id", "held_out", "score", "predicted", "hits"])

    held = (fold(F.col("doc_id"), folds) == held_out).alias("held_out")
    return docs.select(F.col("doc_id").cast("long"), held, F.col("text").cast("string")).mapInArrow(run, "doc_id long, held_out boolean, score double, predicted int, hits boolean")
