"""Language identification by multilingual mixtures.

Each language has a hashed character-trigram model, which gives every word a likelihood; a document is a mixture of languages whose
proportions expectation-maximisation estimates from its words. The set of languages is chosen by penalised likelihood: the
likeliest 1, 2, ... languages are refitted, and each beyond the first must earn half a log of the words; a document's sets grow as long
as that pays.
"""

from __future__ import annotations

import re
from collections.abc import Iterator
from dataclasses import dataclass

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F
from pyspark.sql import types as T

from seqstat.llm.shared import fold

WORD = re.compile(r"[^\W\d_]+")
UNKNOWN = "und"
BITS = 18


def trigram_rows(words: list[str]) -> tuple[np.ndarray, np.ndarray]:
    """Hashed trigrams of each word between two spaces, in word order, and the place of each word's first."""
    codes = np.frombuffer((" " + " ".join(words) + "  ").encode("utf-32-le", "surrogatepass"), np.uint32).astype(np.uint64)
    lengths = np.fromiter(map(len, words), np.int64, len(words))
    hashed = (codes[:-2] * np.uint64(0x9E3779B1) + codes[1:-1] * np.uint64(0x85EBCA77) + codes[2:] * np.uint64(0xC2B2AE3D)) * np.uint64(0x9E3779B97F4A7C15)
    hashed >>= np.uint64(64 - BITS)
    keep = np.ones(int(lengths.sum() + len(words)), bool)
    keep[np.cumsum(lengths + 1) - 1] = False  # the trigram across two words
    return hashed[: len(keep)][keep].astype(np.int64), np.concatenate([[0], np.cumsum(lengths)[:-1]])


@dataclass
class Models:
    """Log probabilities (bucket, language) of trigrams, and the languages."""

    table: np.ndarray
    languages: list[str]

    def words(self, words: list[str]) -> np.ndarray:
        """Log-likelihood of each word under each language."""
        if not words:
            return np.zeros((0, len(self.languages)), np.float32)
        rows, starts = trigram_rows(words)
        return np.add.reduceat(self.table[rows], starts, axis=0)


def train(rows: list[tuple[str, str]], smoothing: float = 0.5) -> Models:
    """Trigram models of (language, text) rows."""
    languages = sorted({lang for lang, _ in rows})
    counts = np.full((1 << BITS, len(languages)), smoothing)
    for lang, text in rows:
        if words := WORD.findall(text.lower()):
            counts[:, languages.index(lang)] += np.bincount(trigram_rows(words)[0], minlength=1 << BITS)
    return Models(np.log(counts / counts.sum(axis=0)).astype(np.float32), languages)


class WordCache(dict):
    """Word → row of a growing matrix of likelihoods; emptied when it would hold more than ``most`` words, the matrix being used anew."""

    def __init__(self, models: Models, most: int = 300_000):
        self.models, self.most = models, most
        self.matrix, self.used = np.zeros((1024, len(models.languages)), np.float32), 0

    def rows(self, words: list[str]) -> np.ndarray:
        new = [w for w in dict.fromkeys(words) if w not in self]
        if self.used + len(new) > self.most:
            self.clear()
            self.used, new = 0, list(dict.fromkeys(words))
        if new:
            while len(self.matrix) < self.used + len(new):
                self.matrix = np.concatenate([self.matrix, np.zeros_like(self.matrix)])
            self.matrix[self.used : self.used + len(new)] = self.models.words(new)
            self.update(zip(new, range(self.used, self.used + len(new)), strict=True))
            self.used += len(new)
        return self.matrix[np.fromiter(map(self.__getitem__, words), np.int64, len(words))]


def mixtures(logs: np.ndarray, starts: np.ndarray, allowed: np.ndarray, turns: int) -> tuple[np.ndarray, np.ndarray]:
    """Proportions (document, language) and log-likelihoods of documents, of which ``starts`` are the first words."""
    sizes = np.diff(np.append(starts, len(logs)))
    doc = np.repeat(np.arange(len(starts)), sizes)
    top = logs.max(axis=1, keepdims=True)
    likely = np.exp(logs - top)
    share = allowed / allowed.sum(axis=1, keepdims=True)
    for _ in range(turns):
        part = likely * share[doc]
        part /= np.maximum(part.sum(axis=1, keepdims=True), 1e-30)
        share = np.add.reduceat(part, starts, axis=0) / sizes[:, None]
    total = np.log(np.maximum((likely * share[doc]).sum(axis=1), 1e-30)) + top[:, 0]
    return share, np.add.reduceat(total, starts)


def rows_of(starts: np.ndarray, total: int, chosen: np.ndarray) -> tuple[np.ndarray, np.ndarray]:
    """Rows of the words of the chosen documents, and the places of their first words among these."""
    sizes = np.diff(np.append(starts, total))
    first = np.concatenate([[0], np.cumsum(sizes[chosen])[:-1]]).astype(np.int64)
    return np.arange(int(sizes[chosen].sum())) + np.repeat(starts[chosen] - first, sizes[chosen]), first


def identify(logs: np.ndarray, starts: np.ndarray, turns: int = 12) -> tuple[np.ndarray, np.ndarray, np.ndarray]:
    """Per document the language, its share of the full mixture, and the number of languages chosen, of which there may be any."""
    n = logs.shape[1]
    full, _ = mixtures(logs, starts, np.ones((len(starts), n), np.float32), turns)
    order = np.argsort(-full, axis=1, kind="stable")
    penalty = 0.5 * np.log(np.diff(np.append(starts, len(logs))) + 1.0)
    best, value, size = order[:, 0].copy(), np.full(len(starts), -np.inf), np.zeros(len(starts), np.int64)
    live = np.arange(len(starts))  # documents whose last set paid
    for k in range(1, n + 1):
        rows, first = rows_of(starts, len(logs), live)
        allowed = np.zeros((len(live), n), np.float32)
        np.put_along_axis(allowed, order[live, :k], 1, axis=1)
        share, fit = mixtures(logs[rows], first, allowed, turns if k > 1 else 0)
        gain = fit - (k - 1) * penalty[live]
        better = gain > value[live]
        live = live[better]
        value[live], best[live], size[live] = gain[better], share[better].argmax(axis=1), k
        if not len(live):
            break
    return best, full[np.arange(len(best)), best], size


def training_rows(docs: DataFrame, held_out: int, folds: int, sample: int, excerpt: int, seed: int, most: int = 1000) -> list[tuple[str, str]]:
    """About ``sample`` labelled rows outside the held-out fold, shared evenly by the ``most`` commonest languages (a bound of the model's
    size), chosen by a hash of the id."""
    labelled = docs.where(F.col("lang").isNotNull() & F.col("text").isNotNull() & (fold(F.col("doc_id"), folds) != held_out))
    counts = {r["lang"]: r["count"] for r in labelled.groupBy("lang").count().orderBy(F.desc("count"), "lang").limit(most).collect()}
    if not counts:
        return []
    each = max(20, sample // len(counts))
    limits = F.create_map(*[x for lang, n in counts.items() for x in (F.lit(lang), F.lit(min(1.0, each / n)))])
    drawn = F.pmod(F.xxhash64(F.lit(seed), "doc_id"), F.lit(1 << 30)) / float(1 << 30)
    rows = labelled.where(drawn < limits[F.col("lang")]).select("lang", F.substring("text", 1, excerpt).alias("text"))
    return [(r["lang"], r["text"]) for r in rows.collect()]


def language_mixtures(docs: DataFrame, held_out: int = 2, folds: int = 4, sample: int = 4000, excerpt: int = 4000, seed: int = 17, block: int = 400, also: tuple[str, ...] = ()) -> DataFrame:
    """(doc_id, held_out, lang_pred, score, n_languages) for every row, and the columns ``also`` as they are.

    Trained on the first ``excerpt`` characters of about ``sample`` labelled rows of the other folds; every whole text is
    read. A null text, or one without a letter, is ``und`` with score 0, as is every text where there is no labelled row; ties
    between languages go to the first by name; repeated rows agree; an empty table gives no rows.
    """
    rows = training_rows(docs, held_out, folds, sample, excerpt, seed)
    models = docs.sparkSession.sparkContext.broadcast(train(rows)) if rows else None
    held = (fold(F.col("doc_id"), folds) == held_out).alias("held_out")
    source = docs.select(F.col("doc_id").cast("long"), held, F.col("text").cast("string"), *[c for c in also if c not in ("doc_id", "text")])
    kept = [f for f in source.schema.fields if f.name != "text" or "text" in also]
    names_out = [*[f.name for f in kept], "lang_pred", "score", "n_languages"]
    schema = T.StructType(list(kept)).add("lang_pred", "string").add("score", "double").add("n_languages", "long")

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        cache = WordCache(models.value) if models else None
        for batch in batches:
            for first in range(0, batch.num_rows, block):
                part = batch.slice(first, block)
                n, texts = part.num_rows, part.column("text")
                names, scores, sizes = [UNKNOWN] * n, np.zeros(n), np.zeros(n, np.int64)
                at, logs = [], []
                for i in range(n if cache is not None else 0):
                    text = texts[i].as_py() or ""
                    if any(c.isalpha() for c in text) and (words := WORD.findall(text.lower())):
                        at.append(i)
                        logs.append(cache.rows(words))
                if at:
                    starts = np.concatenate([[0], np.cumsum([len(x) for x in logs])[:-1]])
                    best, score, size = identify(np.concatenate(logs), starts)
                    scores[at], sizes[at] = np.clip(score, 0, 1), size
                    for i, b in zip(at, best, strict=True):
                        names[i] = models.value.languages[b]
                columns = [part.column(f.name) for f in kept]
                yield pa.RecordBatch.from_arrays([*columns, pa.array(names, pa.string()), pa.array(scores), pa.array(sizes)], names_out)

    return source.mapInArrow(run, schema)


def keep_known(docs: DataFrame) -> DataFrame:
    """The rows of ``docs``, all columns, for which a set of learned languages was chosen, of whatever size and shares.

    Null texts and texts without a letter go. A text in a language that no row is labelled with is read as the nearest learned one
    and stays. A row goes through the model with its columns, so that no text crosses the network to meet its verdict.
    """
    judged = language_mixtures(docs, also=tuple(docs.columns)).where((F.col("lang_pred") != UNKNOWN) & F.col("text").rlike(r"\p{L}"))
    return judged.select(*[F.col(f.name).cast(f.dataType) for f in docs.schema.fields])
