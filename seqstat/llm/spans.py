"""Spans of text: kinds found by patterns, their order, digests and overlaps. Offsets are code points, ends exclusive."""

from __future__ import annotations

import re
from collections.abc import Callable, Iterator
from dataclasses import dataclass

from pyspark.sql import DataFrame
from pyspark.sql import functions as F

Span = tuple[int, int, str]


@dataclass(frozen=True)
class Kind:
    """A named pattern; matches that ``accept`` refuses are dropped after the search has moved past them."""

    name: str
    pattern: re.Pattern
    accept: Callable[[re.Match], bool]

    def find(self, text: str) -> Iterator[Span]:
        for m in self.pattern.finditer(text):
            if self.accept(m):
                yield m.start(), m.end(), self.name


def ordered(spans: list[Span], names: list[str]) -> list[Span]:
    return sorted(spans, key=lambda s: (s[0], names.index(s[2])))


def outside(found: list[Span], base: list[Span]) -> list[Span]:
    """The spans of ``found`` that overlap none of ``base``; both sorted by start."""
    out, i, reach = [], 0, -1
    for s in sorted(found):
        while i < len(base) and base[i][0] < s[1]:
            reach = max(reach, base[i][1])
            i += 1
        if s[0] >= reach:
            out.append(s)
    return out


def digest(found: DataFrame, base: list[str], prefix: str = "n_") -> DataFrame:
    """Counts of the base kinds, the sha256 of their spans and all spans, of the rows of a span finder."""
    spans = F.col("found")
    line = lambda s: F.concat_ws(":", s["kind"], s["start"], s["end"])
    inside = F.filter(spans, lambda s: s["kind"].isin(base))

    def count(kind: str):
        return F.size(F.filter(spans, lambda s: s["kind"] == kind)).cast("long").alias(prefix + kind)

    counts = [count(k) for k in base]
    return found.select("doc_id", *counts, F.sha2(F.array_join(F.transform(inside, line), ","), 256).alias("base_sha256"), F.array_join(F.transform(spans, line), ",").alias("spans"))
