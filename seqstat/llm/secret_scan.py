"""Secrets: fixed patterns, and strings that look random under two character Markov models.

One model is trained on random strings (secrets found by the patterns in a bounded sample, and generated ones), the other on
ordinary words and identifiers of the sample. A run of key characters is a secret if its log-likelihood ratio a character
exceeds a threshold set from labelled strings kept out of training. Words of the sample that no pattern covers can be keys
themselves: those that look random under a first fit are left out of the ordinary class and of its fit.
"""

from __future__ import annotations

import re
import string
from collections.abc import Iterator
from dataclasses import dataclass

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from seqstat.llm.shared import sample_rows
from seqstat.llm.spans import Kind, Span, ordered, outside

#: The contract's patterns.
ASSIGN = re.compile(r"""((?i:password|passwd|secret|token|api_?key))["']?\x20*[:=]\x20*["']?([A-Za-z0-9+/_.=-]+)""", re.ASCII)
ACCESS = re.compile(r"AKIA[A-Z0-9]+")
HEX = re.compile(r"(?<![0-9a-f])[0-9a-f]{24,}")
KEYWORDS = ("password", "passwd", "secret", "token", "apikey", "api_key")

BASE = [
    Kind("assign", ASSIGN, lambda m: len(m[2]) >= 6),
    Kind("access", ACCESS, lambda m: len(m[0]) >= 20),
    Kind("hex", HEX, lambda m: True),
]
NAMES = [k.name for k in BASE] + ["random"]
ALPHABET = string.ascii_letters + string.digits + "+/_=-"
CANDIDATE = re.compile(r"(?<![A-Za-z0-9+/_=-])[A-Za-z0-9+/_=-]{20,}")
WORD = re.compile(r"[A-Za-z0-9+/_=-]{4,}")
_CODES = np.zeros(128, np.int64)
_CODES[[ord(c) for c in ALPHABET]] = np.arange(len(ALPHABET))


def base_spans(text: str) -> list[Span]:
    lowered = text.lower()
    found = []
    for kind in BASE:
        if kind.name != "assign" or any(k in lowered for k in KEYWORDS):
            found += kind.find(text)
    return ordered(found, NAMES)


def codes(s: str) -> np.ndarray:
    return _CODES[np.frombuffer(s.encode("ascii"), np.uint8)]


def transitions(strings: list[str], smoothing: float = 0.5) -> np.ndarray:
    """Log probabilities of the next character given the last, smoothed towards all characters alike."""
    n = len(ALPHABET)
    counts = np.full((n, n), smoothing)
    for s in strings:
        c = codes(s)
        np.add.at(counts, (c[:-1], c[1:]), 1)
    return np.log(counts / counts.sum(axis=1, keepdims=True))


@dataclass
class RandomStrings:
    """log P(next | last, random) - log P(next | last, ordinary), and the least mean of it that counts as random."""

    ratio: np.ndarray
    threshold: float

    def score(self, s: str) -> float:
        c = codes(s)
        return float(self.ratio[c[:-1], c[1:]].mean()) if len(c) > 1 else -np.inf

    def find(self, text: str) -> Iterator[Span]:
        for m in CANDIDATE.finditer(text):
            if self.score(m[0]) > self.threshold:
                yield m.start(), m.end(), "random"


def generated(n: int, seed: int = 7) -> list[str]:
    """Random strings over the alphabets that keys are written in."""
    rng = np.random.default_rng(seed)
    kinds = ["0123456789abcdef", string.ascii_letters + string.digits, string.ascii_uppercase + string.digits, ALPHABET[:64]]
    return ["".join(rng.choice(list(kinds[i % len(kinds)]), int(rng.integers(20, 65)))) for i in range(n)]


def identifiers(plain: list[str], seed: int) -> list[str]:
    """Words of a list joined by threes."""
    rng = np.random.default_rng(seed)
    names = []
    for i in range(min(4000, len(plain))):
        parts = [plain[j] for j in rng.integers(0, len(plain), 3)]
        names.append(["_", "-", ""][i % 3].join(p.capitalize() if i % 3 == 2 else p for p in parts))
    return [*names, "the_first_value", "getNextElement", "index-of-last-item"]


def train(texts: list[str], seed: int = 7, rounds: int = 3, least: int = 12) -> RandomStrings:
    """Fit on the base spans (random) and the other words, also joined as identifiers (ordinary), of some texts.

    After every round but the last, words of ``least`` characters or more leave the ordinary class if they score nearer to random
    strings than to the median ordinary one. The threshold lies halfway between the 99 % quantile of ordinary strings and the 5 %
    quantile of random ones, both held out and of 20 characters or more: a few mislabelled strings on either side don't move it far.
    It is 0 at least, so that transitions that neither class has don't count as random.
    """
    found, words = [], set()
    for text in texts:
        spans = base_spans(text)
        found += [text[a:b].split("=")[-1].split(":")[-1].strip(" \"'") for a, b, _ in spans]
        words.update(text[a:b] for a, b, _ in outside([(m.start(), m.end(), "") for m in WORD.finditer(text)], spans))
    plain = sorted(w for w in words if sum(c.isdigit() for c in w) * 4 < len(w))
    keys = [s for s in found if len(s) > 1 and all(c in ALPHABET for c in s)] + generated(2000, seed)
    random_ones = transitions(keys[::2])
    for n in range(rounds):
        ordinary = plain + identifiers(plain, seed)
        model = RandomStrings(random_ones - transitions(ordinary[::2]), 0.0)
        held = [np.array([model.score(s) for s in strings[1::2] if len(s) >= 20] or [0.0]) for strings in (ordinary, keys)]
        high = float(np.quantile(held[1], 0.05))
        if n + 1 < rounds:
            cut = (float(np.median(held[0])) + high) / 2
            plain = [w for w in plain if len(w) < least or model.score(w) <= cut]
    low = float(np.quantile(held[0], 0.99))
    model.threshold = max(0.0, low + max(0.0, high - low) / 2)
    return model


def find_secrets(docs: DataFrame, sample: int = 2000, excerpt: int = 8192, seed: int = 7) -> DataFrame:
    """(doc_id, spans array of (start, end, kind), n_base) for every row; extra spans never overlap base ones.

    The models are fitted on the first ``excerpt`` characters of ``sample`` rows chosen by a hash of the id; every whole text is
    scanned. Null counts as empty; spans that start together come in the order of the kinds; an empty table gives no rows.
    """
    rows = sample_rows(docs.select("doc_id", F.substring("text", 1, excerpt).alias("text")), sample, seed)
    model = train([r["text"] or "" for r in rows], seed)

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in batches:
            out = []
            for text in batch.column(1):
                text = text.as_py() or ""
                base = base_spans(text)
                extra = outside(list(model.find(text)), base)
                out.append([{"start": a, "end": b, "kind": k} for a, b, k in ordered(base + extra, NAMES)])
            kind = pa.list_(pa.struct([("start", pa.int64()), ("end", pa.int64()), ("kind", pa.string())]))
            yield pa.RecordBatch.from_arrays([batch.column(0), pa.array(out, kind)], ["doc_id", "found"])

    return docs.select(F.col("doc_id").cast("long"), F.col("text").cast("string")).mapInArrow(run, "doc_id long, found array<struct<start:long,end:long,kind:string>>")
