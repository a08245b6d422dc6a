"""Direct counting over keys: every n-gram of a batch is one 64-bit word, made, sorted and added up by columns."""

from __future__ import annotations

from collections.abc import Callable, Iterator

import numpy as np
import pyarrow as pa

#: N-grams and terms that one step holds; parts by a key's first bits, each of which one step adds up.
STEP_GRAMS, STEP_TERMS, SLOT_BITS = 2 << 20, 4 << 20, 12
#: The low bits of a word hold how often its key occurs; the others are the key.
COUNT_BITS = 8
MOST = (1 << COUNT_BITS) - 1
KEY = np.uint64(~MOST & 0xFFFFFFFFFFFFFFFF)
#: Bits of the filter for each key, and its greatest size as a power of 2.
FILTER_BITS, FILTER_MOST = 32, 29
ODD = np.uint64(0x9E3779B97F4A7C15)


def spread(ids: np.ndarray) -> np.ndarray:
    """A random-looking word for each id."""
    x = ids.astype(np.uint64) * ODD
    x ^= x >> np.uint64(30)
    x *= np.uint64(0xBF58476D1CE4E5B9)
    x ^= x >> np.uint64(27)
    x *= np.uint64(0x94D049BB133111EB)
    x ^= x >> np.uint64(31)
    return x


def longer(key: np.ndarray, word: np.ndarray) -> np.ndarray:
    """Keys of grams that go on by one term, from the terms' words."""
    key = (key ^ word) * ODD
    key ^= key >> np.uint64(32)
    return key


def steps(batches: Iterator[pa.RecordBatch], sigma: int, turn: int, turns: int, most: int = STEP_GRAMS) -> Iterator[tuple[np.ndarray, np.ndarray, np.ndarray, np.ndarray]]:
    """(ids, words, places, lengths): the places whose first term falls to ``turn`` and the greatest length of a gram there. About ``most`` grams at
    a time, so a run of any length is cut into steps."""

    def cut(parts: list) -> Iterator[tuple]:
        ids, words, left = (np.concatenate(x) for x in zip(*parts, strict=True))
        places = np.flatnonzero(left)
        lengths = left[places]
        part = np.cumsum(lengths, dtype=np.int64) // most
        for at, n in zip(*(np.split(x, np.flatnonzero(np.diff(part)) + 1) for x in (places, lengths)), strict=True):
            if len(at):
                yield ids, words, at, n

    parts, grams, terms = [], 0, 0
    for batch in batches:
        column = batch.column("ids")
        ids = column.flatten().to_numpy()
        sizes = np.diff(column.offsets.to_numpy())
        words = spread(ids)
        left = np.minimum(np.repeat(np.cumsum(sizes), sizes) - np.arange(len(ids)), sigma)
        if turns > 1:
            left[(words >> np.uint64(33)) % np.uint64(turns) != turn] = 0
        parts.append((ids, words, left))
        grams, terms = grams + int(left.sum()), terms + len(ids)
        if grams >= most or terms >= STEP_TERMS:
            yield from cut(parts)
            parts, grams, terms = [], 0, 0
    if parts:
        yield from cut(parts)


def keys(words: np.ndarray, at: np.ndarray, left: np.ndarray) -> np.ndarray:
    """The key of every gram that begins at ``at``, of one to ``left`` terms."""
    out, filled, n = np.empty(int(left.sum()), np.uint64), 0, 0
    key = np.zeros(len(at), np.uint64)
    while len(at):
        key = longer(key, words[at + n])
        out[filled : filled + len(at)] = key
        filled, n = filled + len(at), n + 1
        more = left > n
        if not more.all():
            at, key, left = at[more], key[more], left[more]
    return out & KEY


def added(found: np.ndarray) -> np.ndarray:
    """Words of the keys ``found``, sorted: each key once with its number, or as often as the number needs."""
    found.sort()
    firsts = np.flatnonzero(np.append(True, found[1:] != found[:-1]))
    number = np.diff(np.append(firsts, len(found)))
    times = -(-number // MOST)
    out = np.repeat(found[firsts], times)
    count = np.full(len(out), MOST, np.uint64)
    count[np.cumsum(times) - 1] = number - (times - 1) * MOST
    return out | count


def dealt(batches: Iterator[pa.RecordBatch], sigma: int, turn: int, turns: int) -> Iterator[pa.RecordBatch]:
    """(slot, words): all grams' words, combined within a step, by slots of their keys."""
    slots = np.arange(1 << SLOT_BITS, dtype=np.int32)
    borders = slots[1:].astype(np.uint64) << np.uint64(64 - SLOT_BITS)
    for _, words, at, left in steps(batches, sigma, turn, turns):
        found = added(keys(words, at, left))
        ends = np.concatenate([[0], np.searchsorted(found, borders), [len(found)]])
        blobs = pa.Array.from_buffers(pa.binary(), len(slots), [None, pa.py_buffer((ends * 8).astype(np.int32)), pa.py_buffer(found)])
        yield pa.RecordBatch.from_arrays([pa.array(slots), blobs], ["slot", "words"]).filter(pa.array(np.diff(ends) > 0))


def frequent(found: np.ndarray, tau: int) -> np.ndarray:
    """The keys whose numbers sum up to ``tau`` at least."""
    found.sort()
    own = found & KEY
    firsts = np.flatnonzero(np.append(True, own[1:] != own[:-1]))
    return own[firsts][np.add.reduceat(found & np.uint64(MOST), firsts) >= tau]


def settled(batches: Iterator[pa.RecordBatch], tau: int) -> Iterator[pa.RecordBatch]:
    """(keys): those of frequent grams, from rows (slot, words) sorted by slot; one slot is held at a time."""

    def row(parts: list[np.ndarray]) -> pa.RecordBatch:
        return pa.RecordBatch.from_arrays([pa.array([frequent(np.concatenate(parts), tau).tobytes()], pa.binary())], ["keys"])

    last, held = None, []
    for batch in batches:
        if not batch.num_rows:
            continue
        slot, column = batch.column("slot").to_numpy(), batch.column("words")
        ends = np.frombuffer(column.buffers()[1], np.int32)[column.offset : column.offset + len(column) + 1].astype(np.int64)
        data = np.frombuffer(column.buffers()[2], np.uint8)
        firsts = np.flatnonzero(np.append(True, np.diff(slot) != 0))
        for a, b in zip(firsts, np.append(firsts[1:], len(slot)), strict=True):
            if slot[a] != last and held:
                yield row(held)
                held = []
            last = slot[a]
            held.append(data[ends[a] : ends[b]].view(np.uint64).copy())
    if held:
        yield row(held)


def bits(key: np.ndarray, size: int) -> np.ndarray:
    """Places in a filter of 2 ** size bits."""
    return ((key & KEY) * ODD >> np.uint64(64 - size)).astype(np.int64)


def filled(blobs: Iterator[bytes], number: int) -> tuple[np.ndarray, int]:
    """A filter that holds the keys of all blobs, and its size: a smaller one lets more grams through, never fewer."""
    size = min(FILTER_MOST, max(16, (FILTER_BITS * number).bit_length()))
    held = np.zeros(1 << (size - 3), np.uint8)
    for blob in blobs:
        at = bits(np.frombuffer(blob, np.uint64), size)
        np.bitwise_or.at(held, at >> 3, (1 << (at & 7)).astype(np.uint8))
    return held, size


def passed(batches: Iterator[pa.RecordBatch], sigma: int, turn: int, turns: int, known: Callable[[], tuple[np.ndarray, int]]) -> Iterator[pa.RecordBatch]:
    """(ids, cf): the grams that the filter lets through, combined within a step. Within a step a gram is named by the name of the gram one
    term shorter and its last term, so equal names are equal grams and no key is trusted. What goes on from a gram that isn't frequent isn't either."""
    held, size = known()
    for ids, words, at, left in steps(batches, sigma, turn, turns):
        key, name, n = np.zeros(len(at), np.uint64), np.zeros(len(at), np.int64), 0
        while len(at):
            key = longer(key, words[at + n])
            place = bits(key, size)
            hit = (held[place >> 3] >> (place & 7).astype(np.uint8)) & 1 == 1
            at, key, name, left = at[hit], key[hit], name[hit], left[hit]
            if not len(at):
                break
            exact = name << 32 | ids[at + n]
            order = np.argsort(exact)
            exact = exact[order]
            new = np.append(True, exact[1:] != exact[:-1])
            name[order] = np.cumsum(new) - 1
            firsts, n = np.flatnonzero(new), n + 1
            flat = ids[(at[order[firsts]][:, None] + np.arange(n)).ravel()]
            lists = pa.ListArray.from_arrays(pa.array(np.arange(0, len(flat) + 1, n), pa.int32()), pa.array(flat))
            yield pa.RecordBatch.from_arrays([lists, pa.array(np.diff(np.append(firsts, len(exact))), pa.int64())], ["ids", "cf"])
            more = left > n
            at, key, name, left = at[more], key[more], name[more], left[more]
