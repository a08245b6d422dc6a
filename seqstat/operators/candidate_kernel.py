"""Candidates of the level-wise scan where their overlaps meet: rows of one overlap are its grams to the left, to the right, and its windows."""

from __future__ import annotations

from collections.abc import Iterator

import numpy as np
import pyarrow as pa

LEFT, RIGHT, WINDOW = 0, 1, 2
#: Candidates that are made at a time.
BLOCK = 2 << 20
TERM = (1 << 32) - 1


def overlaps(batches: Iterator[pa.RecordBatch], keys: list[str]) -> Iterator[list[np.ndarray]]:
    """Columns of ``keys``, kind and word over whole overlaps, from rows sorted by all of them."""
    held = []
    for batch in batches:
        if not batch.num_rows:
            continue
        columns = [batch.column(c).to_numpy() for c in (*keys, "kind", "word")]
        changes = np.zeros(batch.num_rows - 1, bool)
        for column in columns[: len(keys)]:
            changes |= column[1:] != column[:-1]
        own = int(np.flatnonzero(changes).max(initial=-1)) + 1
        going = held and all(held[-1][j][-1] == columns[j][0] for j in range(len(keys)))
        if own or (held and not going):
            yield [np.concatenate(x) for x in zip(*held, [c[:own] for c in columns], strict=True)]
            held = []
        held.append([c[own:] for c in columns])
    if held:
        yield [np.concatenate(x) for x in zip(*held, strict=True)]


def numbers(keys: list[np.ndarray]) -> np.ndarray:
    """The number of each row's overlap."""
    new = np.zeros(len(keys[0]), bool)
    for column in keys:
        new[1:] |= column[1:] != column[:-1]
    return np.cumsum(new)


def candidates(left: np.ndarray, right: np.ndarray, lasts: np.ndarray) -> Iterator[tuple[int, int, np.ndarray]]:
    """(from, to, words): every candidate that the grams ``from`` to ``to`` on the left begin, as that gram's place and the last term, in order.
    ``left`` and ``right`` are the overlaps' numbers of the grams on either side, ``lasts`` the last terms of those on the right."""
    if not len(left) or not len(right):
        return
    size = np.bincount(right, minlength=int(max(left[-1], right[-1])) + 1)
    each, begins = size[left], (np.cumsum(size) - size)[left]
    cuts = np.flatnonzero(np.diff(np.cumsum(each) // BLOCK)) + 1
    for a, b in zip(np.append(0, cuts), np.append(cuts, len(left)), strict=True):
        n = each[a:b]
        at = np.arange(n.sum()) + np.repeat(begins[a:b] - (np.cumsum(n) - n), n)
        yield int(a), int(b), np.repeat(np.arange(a, b), n) << 32 | lasts[at]


def batch(columns: list[np.ndarray], **more: np.ndarray) -> pa.RecordBatch:
    flat = np.stack(columns, 1).astype(np.int32).ravel()
    lists = pa.ListArray.from_arrays(pa.array(np.arange(0, len(flat) + 1, len(columns)), pa.int32()), pa.array(flat))
    return pa.RecordBatch.from_arrays([lists, *[pa.array(x, pa.int64()) for x in more.values()]], ["ids", *more])


def made(batches: Iterator[pa.RecordBatch], keys: list[str]) -> Iterator[pa.RecordBatch]:
    """(ids): a row for each candidate."""
    for *own, kind, word in overlaps(batches, [*keys, "salt"]):
        group = numbers(own)
        left, right = np.flatnonzero(kind == LEFT), np.flatnonzero(kind == RIGHT)
        for _, _, found in candidates(group[left], group[right], word[right]):
            of = left[found >> 32]
            yield batch([word[of] >> 32, *[c[of] for c in own[:-1]], found & TERM])


def counted(batches: Iterator[pa.RecordBatch], keys: list[str], tau: int) -> Iterator[pa.RecordBatch]:
    """(ids, cf): how often the candidates occur, for those that do so ``tau`` times or more: all candidates of an overlap are made, and its windows
    looked up in them."""
    for *own, kind, word in overlaps(batches, [*keys, "salt"]):
        group = numbers(own)
        left, right, seen = (np.flatnonzero(kind == x) for x in (LEFT, RIGHT, WINDOW))
        if not len(left) or not len(seen):
            continue
        new = np.append(True, (np.diff(word[seen]) != 0) | (np.diff(group[seen]) != 0))
        cf = np.diff(np.append(np.flatnonzero(new), len(seen)))
        seen = seen[new]
        heads, mine = group[left] << 32 | word[left] >> 32, group[seen] << 32 | word[seen] >> 32
        place = np.minimum(np.searchsorted(heads, mine), len(heads) - 1)
        known = heads[place] == mine
        seen, cf, wanted = seen[known], cf[known], place[known] << 32 | word[seen[known]] & TERM
        for a, b, found in candidates(group[left], group[right], word[right]):
            lo, hi = np.searchsorted(wanted, [a << 32, b << 32])
            at = np.searchsorted(found, wanted[lo:hi])
            inside = at < len(found)
            inside[inside] = found[at[inside]] == wanted[lo:hi][inside]
            often = lo + np.flatnonzero(inside & (cf[lo:hi] >= tau))
            if len(often):
                of = seen[often]
                yield batch([word[of] >> 32, *[c[of] for c in own[:-1]], word[of] & TERM], cf=cf[often])
