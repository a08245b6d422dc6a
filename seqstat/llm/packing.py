"""Best-fit packing of token sequences by exact-complement hashing.

Pieces of one length are interchangeable, so the plan is made from the counts by length alone: at most ``capacity`` numbers,
whatever the input. Sums of one, two and three available lengths are indexed as bit sets; the longest piece opens a sequence,
a combination that fills its gap exactly is consumed under the counts as often as they allow, and where none exists the longest
piece that fits goes in (best fit). The plan gives each length intervals of ranks; a piece finds its sequence and offset from its
rank among the pieces of its length.
"""

from __future__ import annotations

import re
import zlib
from collections import Counter
from collections.abc import Iterator
from functools import lru_cache

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from seqstat.llm.prefix import grouped_offsets
from seqstat.llm.shared import stage

#: Texts of these characters alone are split here; all others by the library itself.
_PLAIN = re.compile("[^\t\n\r \x21-\x7e¡§«°»¿-įı-ɏ]")
#: Fixed value: the split pattern of the tokenizer file, for plain texts.
_SPLIT = re.compile(r"'s|'t|'re|'ve|'m|'ll|'d|[^\W\d_]+|[0-9]|(?:[^\w\s]|_)+")


def byte_characters() -> dict[int, str]:
    """The printable stand-in of each byte in byte-level vocabularies: itself if printable, else 256 and up in order."""
    printable = [*range(0x21, 0x7F), *range(0xA1, 0xAD), *range(0xAE, 0x100)]
    others = (b for b in range(256) if b not in set(printable))
    return {b: chr(b) for b in printable} | {b: chr(256 + i) for i, b in enumerate(others)}


class WordIds(dict):
    """Word → its ids as little-endian unsigned 32-bit integers; emptied when it holds ``most`` words."""

    def __init__(self, path: str, most: int = 400_000):
        from tokenizers import Tokenizer

        self.whole, self.most = Tokenizer.from_file(path), most
        self.model, self.stand_ins = self.whole.model, byte_characters()
        self.special = [t.content for t in self.whole.get_added_tokens_decoder().values()]

    def __missing__(self, word: str) -> bytes:
        mapped = word.encode().decode("latin-1").translate(self.stand_ins)
        out = np.array([t.id for t in self.model.tokenize(mapped)], "<u4").tobytes()
        if len(self) >= self.most:
            self.clear()
        self[word] = out
        return out

    def encode(self, text: str) -> bytes:
        """Ids of a text as the library gives them without added special tokens."""
        out = []
        for part in segments(text):
            if _PLAIN.search(part) or any(s in part for s in self.special):
                out.append(np.array(self.whole.encode(part, add_special_tokens=False).ids, "<u4").tobytes())
            else:
                out.append(b"".join(map(self.__getitem__, _SPLIT.findall(part.lower()))))
        return b"".join(out)


def segments(text: str, size: int = 1 << 20) -> Iterator[str]:
    """The text in parts of about ``size``, cut before a space, where neither words nor normal forms meet."""
    start = 0
    while len(text) - start > size and (cut := text.find(" ", start + size)) > 0:
        yield text[start:cut]
        start = cut
    yield text[start:]


@lru_cache(maxsize=2)
def load(path: str) -> WordIds:
    return WordIds(path)


def default_model() -> str:
    import public_tokenizers

    return public_tokenizers.path("word_bpe_49k.json")


def pieces(docs: DataFrame, path: str | None = None, capacity: int = 4096, end_id: int = 1) -> DataFrame:
    """(doc_id, piece, start, length, ids_crc32): only documents of more than ``capacity`` tokens are cut."""
    where, last = path or default_model(), int(end_id).to_bytes(4, "little")

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        words, names = load(where), ["doc_id", "piece", "start", "length", "ids_crc32"]
        for batch in batches:
            out: tuple[list, ...] = ([], [], [], [], [])
            for doc, text in zip(batch.column(0).to_pylist(), batch.column(1), strict=True):
                ids = words.encode(text.as_py() or "") + last
                for i, at in enumerate(range(0, len(ids), 4 * capacity)):
                    part = ids[at : at + 4 * capacity]
                    for column, value in zip(out, (doc, i, at // 4, len(part) // 4, zlib.crc32(part)), strict=True):
                        column.append(value)
            kinds = [pa.int64(), pa.int32(), pa.int64(), pa.int64(), pa.int64()]
            yield pa.RecordBatch.from_arrays([pa.array(c, k) for c, k in zip(out, kinds, strict=True)], names)

    return docs.select(F.col("doc_id").cast("long"), F.col("text").cast("string")).mapInArrow(run, "doc_id long, piece int, start long, length long, ids_crc32 long")


class SumIndex:
    """Which totals one, two or three available lengths make, as bit sets."""

    def __init__(self, counts: np.ndarray):
        self.capacity, self.counts = len(counts) - 1, counts
        self.rebuild()

    def rebuild(self) -> None:
        self.lengths = [int(x) for x in np.flatnonzero(self.counts)[::-1]]
        full = (1 << (self.capacity + 1)) - 1
        self.one = sum(1 << x for x in self.lengths)
        self.two = self.three = 0
        for x in self.lengths:
            self.two |= self.one << x
        self.two &= full
        for x in self.lengths:
            self.three |= self.two << x
        self.three &= full

    def complement(self, gap: int, used: Counter) -> list[int] | None:
        """One to three lengths that sum to ``gap``, the longest first, of which enough are left besides ``used``."""
        enough = lambda parts: all(self.counts[x] >= n + used[x] for x, n in Counter(parts).items())
        if self.one >> gap & 1 and enough([gap]):
            return [gap]
        if self.two >> gap & 1:
            for x in self.lengths:
                if 2 * x < gap:
                    break
                if x < gap and self.one >> (gap - x) & 1 and enough([x, gap - x]):
                    return [x, gap - x]
        if self.three >> gap & 1:
            for x in self.lengths:
                if 3 * x < gap:
                    break
                rest = gap - x
                if rest > 1 and self.two >> rest & 1:
                    for y in self.lengths:
                        if 2 * y < rest:
                            break
                        if y <= x and y < rest and self.one >> (rest - y) & 1 and enough([x, y, rest - y]):
                            return [x, y, rest - y]
        return None


def plan(counts: np.ndarray) -> list[tuple[int, list[int]]]:
    """(how often, lengths) patterns that use up ``counts`` (index: length)."""
    counts = counts.astype(np.int64).copy()
    index, out = SumIndex(counts), []
    while index.lengths:
        parts, used = [index.lengths[0]], Counter([index.lengths[0]])
        gap = index.capacity - parts[0]
        while gap:
            if found := index.complement(gap, used):
                parts += found
                used.update(found)
                break
            fit = next((x for x in index.lengths if x <= gap and counts[x] > used[x]), 0)
            if not fit:
                break
            parts.append(fit)
            used[fit] += 1
            gap -= fit
        times = min(int(counts[x]) // n for x, n in used.items())
        for x, n in used.items():
            counts[x] -= times * n
        out.append((times, parts))
        if any(not counts[x] for x in used):
            index.rebuild()
    return out


def intervals(patterns: list[tuple[int, list[int]]]) -> dict[int, np.ndarray]:
    """Length → rows (first rank, first sequence, pieces a sequence, offset) in rank order."""
    given, sequence, out = Counter(), 0, {}
    for times, parts in patterns:
        offset = 0
        for x, n in sorted(Counter(parts).items(), reverse=True):
            out.setdefault(x, []).append((given[x], sequence, n, offset))
            given[x] += times * n
            offset += n * x
        sequence += times
    return {x: np.array(rows, np.int64) for x, rows in out.items()}


def pack(docs: DataFrame, path: str | None = None, capacity: int = 4096, end_id: int = 1) -> DataFrame:
    """Per piece: doc_id, piece, start, length, ids_crc32, sequence_id, offset; sequences hold ``capacity`` tokens at most.

    Null and empty texts are the end id alone; equal lengths and repeated rows are ranked in an arbitrary but gapless order;
    an empty table gives no rows; other columns are ignored.
    """
    spark = docs.sparkSession
    cut = pieces(docs, path, capacity, end_id).withColumn("order", F.pmod(F.xxhash64("doc_id", "piece"), F.lit(1 << 32)))
    cut = stage(cut, "pieces")
    counts = np.zeros(capacity + 1, np.int64)
    for row in cut.groupBy("length").count().collect():  # at most ``capacity`` rows
        counts[row["length"]] = row["count"]
    places = spark.sparkContext.broadcast(intervals(plan(counts)))
    ranked = grouped_offsets(cut, ["length"], None, "order", ["doc_id", "piece"], out="rank")
    names = ["doc_id", "piece", "start", "length", "ids_crc32"]

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in batches:
            length, rank = (batch.column(i).to_numpy(zero_copy_only=False) for i in (3, 5))
            sequence, offset = np.zeros(len(length), np.int64), np.zeros(len(length), np.int64)
            for x in np.unique(length):
                rows = np.flatnonzero(length == x)
                table = places.value[int(x)]
                found = table[np.searchsorted(table[:, 0], rank[rows], side="right") - 1]
                past = rank[rows] - found[:, 0]
                sequence[rows] = found[:, 1] + past // found[:, 2]
                offset[rows] = found[:, 3] + past % found[:, 2] * x
            yield pa.RecordBatch.from_arrays([*batch.columns[:5], pa.array(sequence), pa.array(offset)], [*names, "sequence_id", "offset"])

    return ranked.select(*names, "rank").mapInArrow(run, "doc_id long, piece int, start long, length long, ids_crc32 long, sequence_id long, offset long")
