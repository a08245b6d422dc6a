"""Direct counting by keys: all n-grams are counted by words of fixed width, the frequent ones by their terms."""

import random
from collections import Counter

import numpy as np
import pyarrow as pa
import pytest

from seqstat.functions import text
from seqstat.operators import direct
from seqstat.operators import direct_kernel as kernel
from seqstat.operators.encode import Options, prepare
from seqstat.operators.suffix import suffix_scan

RUNS = [[1, 2, 1, 2, 1, 2, 3], [3], [1] * 700, [2, 1, 2, 1], [3, 3, 2, 1, 2, 1, 2]] * 3


def counts(runs, tau, sigma):
    every = Counter(tuple(r[i : i + n]) for r in runs for i in range(len(r)) for n in range(1, min(sigma, len(r) - i) + 1))
    return {g: c for g, c in every.items() if c >= tau}


def batches(runs, size=2):
    for at in range(0, len(runs), size):
        # A batch that is a slice of a longer column, as Arrow may hand it over.
        column = pa.array([[9], *runs[at : at + size]], pa.list_(pa.int32()))
        yield pa.RecordBatch.from_arrays([column], ["ids"]).slice(1)


def whole(runs, tau, sigma, turns=1):
    """The passes one after another, without a session; a row a batch where slots are settled."""
    found = {}
    for t in range(turns):
        schema = pa.schema({"slot": pa.int32(), "words": pa.binary()})
        rows = pa.Table.from_batches(kernel.dealt(batches(runs), sigma, t, turns), schema).sort_by("slot")
        keys = [x for b in kernel.settled(iter(rows.to_batches(max_chunksize=3)), tau) for x in b.column("keys").to_pylist()]
        held = kernel.filled(iter(keys), sum(map(len, keys)) // 8)
        added = Counter()
        for b in kernel.passed(batches(runs), sigma, t, turns, lambda: held):
            for ids, cf in zip(b.column("ids").to_pylist(), b.column("cf").to_pylist(), strict=True):
                added[tuple(ids)] += cf
        assert not set(found) & set(added)
        found |= added
    return {g: c for g, c in found.items() if c >= tau}


@pytest.mark.parametrize("turns", [1, 3])
@pytest.mark.parametrize("most", [20, 300, 1 << 20])
def test_passes(monkeypatch, turns, most):
    """Runs longer than a step, counts beyond the bits of a word, batches that are slices."""
    monkeypatch.setattr(kernel.steps, "__defaults__", (most,))
    runs = RUNS if most > 20 else [r[:9] for r in RUNS]
    for tau, sigma in ((2, 5), (6, 40), (2000, 3)):
        assert whole(runs, tau, sigma, turns) == counts(runs, tau, sigma)


def test_clashing_keys_count_apart(monkeypatch):
    """With keys of four bits nearly all grams share one: the counts are still each gram's own."""
    monkeypatch.setattr(kernel, "KEY", np.uint64(0xF << 60))
    rng = random.Random(3)
    runs = [[rng.randrange(1, 7) for _ in range(rng.randrange(1, 30))] for _ in range(60)]
    assert whole(runs, 5, 8) == counts(runs, 5, 8)


def test_numbers_beyond_a_word():
    for n in (1, 254, 255, 256, 510, 1000):
        found = kernel.added(np.array([512] * n + [1024], np.uint64))
        assert (found & np.uint64(kernel.MOST)).sum() == n + 1
        assert kernel.frequent(found, n).tolist() == ([512] if n > 1 else [512, 1024])


def test_many_rows_are_keys(spark, monkeypatch):
    """Beyond the bytes no row of terms is made for an n-gram; a run that is counted raw still makes them."""
    rng = random.Random(8)
    p = prepare(text.literal(spark, *[" ".join(f"w{rng.randrange(5)}" for _ in range(rng.randrange(1, 60))) for _ in range(20)]), 2)
    want = {tuple(r["ids"]): r["cf"] for r in suffix_scan(p, 2, 30).collect()}
    monkeypatch.setattr(direct, "gram_rows", None)
    monkeypatch.setattr(direct, "ROW_BYTES", 1000)
    assert {tuple(r["ids"]): r["cf"] for r in direct.direct_count(p, 2, 30).collect()} == want
    assert {tuple(r["ids"]): r["cf"] for r in direct.direct_count(p, 2, 30, turn_bytes=20_000).collect()} == want
    with pytest.raises(TypeError):
        direct.direct_count(p, 2, 30, Options())


def test_long_grams_of_a_query_are_keys(spark, same, monkeypatch):
    """The registered query at sigma 50, all of it by keys, against its SQL."""
    from seqstat import queries

    calls, keyed = [], direct.counted_by_keys
    monkeypatch.setattr(direct, "ROW_BYTES", 1000)
    monkeypatch.setattr(direct, "counted_by_keys", lambda *a: calls.append(a) or keyed(*a))
    same(queries.QUERIES["vary_sigma_50_direct"], queries.ORACLES["vary_sigma_50_direct"])
    assert len(calls) == 1
