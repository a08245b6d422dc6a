"""Token counts of whole texts by a public subword model; huge documents in overlapping chunks that are resynchronised.

A chunk's encoding carries character offsets. Two neighbouring chunks are spliced at a token that both hold: same piece, same
start, same end, and not the first of either. That is safe for a vocabulary whose pairs are merged by rank: an
encoding is the right one exactly if each pair of neighbouring tokens encodes to itself; the pair before the common token
was proven in the left chunk, the pair after it in the right one. Where no token is common, the overlap is doubled,
at last to the whole left chunk.
"""

from __future__ import annotations

from collections.abc import Iterator
from functools import lru_cache

import pyarrow as pa
import pyarrow.compute as pc
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

Token = tuple[int, int, int]


@lru_cache(maxsize=4)
def load(path: str):
    import sentencepiece

    return sentencepiece.SentencePieceProcessor(model_file=path)


def default_model() -> str:
    import public_tokenizers

    return public_tokenizers.path("piece_bpe_32k.model")


def encode_at(model, data: bytes, start: int, end: int) -> list[Token]:
    """(start, end, id) of the tokens of a chunk, in bytes of the whole text."""
    pieces = model.encode(data[start:end].decode(), return_type="proto").pieces
    return [(start + p.begin, start + p.end, p.id) for p in pieces]


def whole_character(data: bytes, at: int) -> int:
    """The start of the character that holds byte ``at``."""
    while 0 < at < len(data) and data[at] & 0xC0 == 0x80:
        at -= 1
    return min(at, len(data))


def common_token(left: list[Token], right: list[Token]) -> tuple[int, int] | None:
    """Places of the last token that both hold (the first of neither, and not an empty one)."""
    at = {t: j for j, t in enumerate(right) if j and t[1] > t[0]}
    least = min(at, default=(0, 0, 0))[0]
    for i in range(len(left) - 1, 0, -1):
        if not at or left[i][1] <= least:
            return None
        if left[i] in at:
            return i, at[left[i]]
    return None


def count_long(model, text: str, chunk: int = 32768, overlap: int = 256) -> int:
    """Tokens of the whole text, as if it were encoded at once."""
    data = text.encode()
    end = whole_character(data, chunk)
    left, first, total = encode_at(model, data, 0, end), 0, 0
    while end < len(data):
        after, width = whole_character(data, end + chunk), overlap
        while True:
            start = whole_character(data, max(first, end - width))
            right = encode_at(model, data, start, after)
            if start > 0 and (found := common_token(left, right)):
                total += found[0]
                first, left = right[found[1]][0], right[found[1] :]
                break
            if start == first:  # nothing in common even with all of the left chunk: encode from the text's start
                total, first, left = 0, 0, encode_at(model, data, 0, after)
                break
            width *= 2
        end = after
    return total + len(left)


def token_counts(docs: DataFrame, path: str | None = None, limit: int = 4096, chunk: int = 32768, overlap: int = 256) -> DataFrame:
    """(doc_id, n_bytes, n_tokens, over_limit) for every row, without begin, end or other added tokens.

    Null counts as empty: 0 bytes and tokens. Texts of over ``chunk`` characters go chunk by chunk, so that memory for tokens doesn't
    follow a document's length; only where two chunks have no token in common, which the counts' exactness then demands, is the text
    encoded anew from its start. Repeated rows each have a row; an empty table gives none; other columns are ignored.
    """
    where = path or default_model()

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        model = load(where)
        for batch in batches:
            texts, counts = batch.column(1).fill_null("").to_pylist(), []
            for i in range(0, len(texts), 256):
                part = texts[i : i + 256]
                short = iter(model.encode([t for t in part if len(t) <= chunk], num_threads=1))
                counts += [len(next(short)) if len(t) <= chunk else count_long(model, t, chunk, overlap) for t in part]
            octets = pc.fill_null(pc.binary_length(batch.column(1)), 0).cast(pa.int64())
            n = pa.array(counts, pa.int64())
            yield pa.RecordBatch.from_arrays([batch.column(0), octets, n, pc.greater(n, limit)], ["doc_id", "n_bytes", "n_tokens", "over_limit"])

    return docs.select(F.col("doc_id").cast("long"), F.col("text").cast("string")).mapInArrow(run, "doc_id long, n_bytes long, n_tokens long, over_limit boolean")
