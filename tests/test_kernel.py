"""The one-pass kernels against plain enumeration, over random corpora, batch sizes and partition cuts."""

import random
from collections import Counter

import numpy as np
import pytest

from seqstat.operators.suffix_kernel import ALL, CLOSED, MAXIMAL, StackKernel, VectorKernel, run


def enumerate_grams(docs, sigma):
    return Counter(tuple(d[i : i + n]) for d in docs for i in range(len(d)) for n in range(1, min(sigma, len(d) - i) + 1))


def feed(rows, size):
    for i in range(0, len(rows), size):
        part = rows[i : i + size]
        yield np.array(sum(part, []), np.int32), np.array([len(r) for r in part], np.int64), np.ones((len(part), 1), np.int64)


def grams_of(kernel, rows, size, cells=1 << 20):
    for flat, lengths, weights, opened, _ in run(kernel, feed(rows, size), cells):
        ends = np.cumsum(lengths)
        for i, n in enumerate(lengths):
            yield tuple(flat[ends[i] - n : ends[i]].tolist()), int(weights[i, 0]), bool(opened[i])


@pytest.mark.parametrize("kind", [VectorKernel, StackKernel])
@pytest.mark.parametrize("keep", [ALL, MAXIMAL, CLOSED])
def test_random_corpora(kind, keep):
    rng = random.Random(7)
    for _ in range(150):
        docs = [[rng.randint(1, 3) for _ in range(rng.randint(0, 12))] for _ in range(rng.randint(1, 8))]
        tau, sigma = rng.randint(1, 5), rng.randint(1, 8)
        rows = sorted((d[i : i + sigma] for d in docs for i in range(len(d))), reverse=True)
        full = {g: c for g, c in enumerate_grams(docs, sigma).items() if c >= tau}
        want = full
        if keep != ALL:
            want = {g: c for g, c in full.items() if not any(h[:-1] == g and (keep == MAXIMAL or full[h] == c) for h in full)}
        assert {g: c for g, c, _ in grams_of(kind(tau, sigma, keep=keep), rows, rng.randint(1, 4), rng.choice([3, 1 << 20]))} == want


@pytest.mark.parametrize("kind", [VectorKernel, StackKernel])
def test_boundary_repair(kind):
    rng = random.Random(8)
    for _ in range(150):
        docs = [[rng.randint(1, 2) for _ in range(rng.randint(1, 12))] for _ in range(rng.randint(1, 8))]
        tau, sigma, parts = rng.randint(1, 5), rng.randint(1, 6), rng.randint(1, 5)
        rows = sorted((d[i : i + sigma] for d in docs for i in range(len(d))), reverse=True)
        cuts = [0, *sorted(rng.randint(0, len(rows)) for _ in range(parts - 1)), len(rows)]
        closed, opened = {}, Counter()
        for a, b in zip(cuts, cuts[1:]):
            n = 0
            for gram, count, is_open in grams_of(kind(tau, sigma, repair=True), rows[a:b], 2):
                if is_open:
                    opened[gram] += count
                    n += 1
                else:
                    assert gram not in closed
                    closed[gram] = count
            assert n <= 2 * sigma
        mended = closed | {g: c for g, c in opened.items() if c >= tau}
        assert mended == {g: c for g, c in enumerate_grams(docs, sigma).items() if c >= tau}


def test_trace_of_the_running_example():
    """Suffixes of b in the example (a 1, b 2, x 3): counts close from the deepest, and the shortest ends at 5."""
    kernel = StackKernel(3, 3)
    kernel.batch(np.array([2, 3, 3, 2, 3, 2, 1, 3, 2], np.int32), np.array([3, 2, 3, 1]), np.array([[1], [1], [2], [1]]))
    kernel.finish()
    assert kernel.trace == [((2, 3, 3), 1), ((2, 3), 2), ((2, 1, 3), 2), ((2, 1), 2), ((2,), 5)]


def test_weights_as_vectors():
    kernel = VectorKernel(1, 2, 2)
    kernel.batch(np.array([2, 1, 2, 1], np.int32), np.array([2, 2]), np.array([[1, 0], [0, 3]]))
    kernel.finish()
    flat, lengths, weights, *_ = kernel.out.take()
    assert sorted(zip(lengths.tolist(), weights.tolist())) == [(1, [1, 3]), (2, [1, 3])]
