"""One pass over suffixes in descending order: all n-gram counts with memory for one path of terms.

Rows arrive as (ids, weights); those that share a prefix stand together, so a prefix is complete when it no longer begins the next
row. The vector kernel finds, for every depth at once, the rows of a batch where the prefix changes and sums weights between
them; what a batch leaves open is carried on. The stack kernel does the same row by row and serves as its control.
"""

from __future__ import annotations

from collections.abc import Iterator
from dataclasses import dataclass, field

import numpy as np

ALL, MAXIMAL, CLOSED = "all", "prefix_maximal", "prefix_closed"


@dataclass
class Emitted:
    """Grams as one array of ids with lengths, their weights (rows of W), whether they may go on in another partition, and the
    largest count of an extension by one term."""

    ids: list[np.ndarray] = field(default_factory=list)
    lengths: list[np.ndarray] = field(default_factory=list)
    weights: list[np.ndarray] = field(default_factory=list)
    opened: list[np.ndarray] = field(default_factory=list)
    best: list[np.ndarray] = field(default_factory=list)

    def add(self, ids: np.ndarray, weights: np.ndarray, opened: np.ndarray, best: np.ndarray) -> None:
        """ids: grams of one length, a row each."""
        if len(ids):
            self.ids.append(ids.ravel())
            self.lengths.append(np.full(len(ids), ids.shape[1], np.int64))
            self.weights.append(weights)
            self.opened.append(opened)
            self.best.append(best)

    def take(self) -> tuple[np.ndarray, np.ndarray, np.ndarray, np.ndarray, np.ndarray]:
        out = tuple(np.concatenate(x) for x in (self.ids, self.lengths, self.weights, self.opened, self.best))
        self.ids, self.lengths, self.weights, self.opened, self.best = [], [], [], [], []
        return out


class VectorKernel:
    """keep: 'all', 'prefix_maximal' or 'prefix_closed'; repair: emit what may go on in a neighbouring partition as open rows."""

    def __init__(self, tau: int, width: int, weights: int = 1, keep: str = ALL, repair: bool = False):
        self.tau, self.keep, self.repair, self.n = tau, keep, repair, weights
        self.path = np.zeros(0, np.int32)  # the last row
        self.counts = np.zeros((width + 1, weights), np.int64)  # of its prefixes, by length
        self.best = np.zeros(width + 1, np.int64)  # largest complete extension by one term
        self.since_start = np.zeros(width + 1, bool)  # whether a prefix began with the partition's first row
        self.started = False
        self.out = Emitted()

    def _grow(self, width: int) -> None:
        more = width + 1 - len(self.best)
        if more > 0:
            self.counts = np.vstack([self.counts, np.zeros((more, self.n), np.int64)])
            self.best = np.concatenate([self.best, np.zeros(more, np.int64)])
            self.since_start = np.concatenate([self.since_start, np.zeros(more, bool)])

    def _emit(self, ids: np.ndarray, counts: np.ndarray, best: np.ndarray, opened: np.ndarray) -> None:
        total = counts.sum(axis=1)
        good = total >= self.tau
        if self.keep == MAXIMAL:
            good &= best < self.tau
        elif self.keep == CLOSED:
            good &= best < total
        good = (good | opened) if self.repair else good
        self.out.add(ids[good], counts[good], opened[good] & self.repair, best[good])

    def batch(self, flat: np.ndarray, lengths: np.ndarray, weights: np.ndarray) -> None:
        """Rows in descending order: their ids one after another, lengths (at least 1) and an (n, weights) array."""
        n = len(lengths)
        if not n:
            return
        width = max(int(lengths.max()), len(self.path))
        self._grow(width)
        rows = np.zeros((n + 1, width), np.int32)  # row 0: the path
        rows[0, : len(self.path)] = self.path
        mask = np.arange(width) < lengths[:, None]
        rows[1:][mask] = flat
        same = (rows[1:] == rows[:-1]) & mask
        common = np.where(same.all(axis=1), width, same.argmin(axis=1)) if width else np.zeros(n, np.int64)
        common = np.minimum(common, np.concatenate([[len(self.path)], lengths[:-1]]))
        if not self.started:
            common[0] = 0
        summed = np.vstack([np.zeros((1, self.n), np.int64), np.cumsum(weights, axis=0)])
        deeper: tuple[np.ndarray, np.ndarray] | None = None  # first row and total of the complete groups one term longer
        new = np.zeros_like(self.counts), np.zeros_like(self.best), np.zeros_like(self.since_start)
        for d in range(width, 0, -1):
            breaks = np.flatnonzero(common < d)
            head = int(breaks[0]) if len(breaks) else n  # rows before it go on with the path
            long = len(self.path) >= d and self.started
            starts = breaks[lengths[breaks] >= d]
            ends = np.append(breaks, n)[np.searchsorted(breaks, starts, side="right")]
            counts = summed[ends] - summed[starts]
            best = np.zeros(len(starts), np.int64)
            first_best = self.best[d]
            if deeper is not None and len(deeper[0]):
                own = np.searchsorted(starts, deeper[0], side="right") - 1
                inside = (own >= 0) & (deeper[0] >= head)
                np.maximum.at(best, own[inside], deeper[1][inside])
                ahead = deeper[1][deeper[0] < head]
                if len(ahead):
                    first_best = max(first_best, int(ahead.max()))
            done_first, done_total = [], []
            if long:
                count = self.counts[d] + summed[head] - summed[0]
                if head < n:
                    self._emit(self.path[None, :d], count[None], np.array([first_best]), self.since_start[d : d + 1].copy())
                    done_first.append(np.array([-1]))
                    done_total.append(np.array([int(count.sum())]))
                else:
                    new[0][d], new[1][d], new[2][d] = count, first_best, self.since_start[d]
            at_start = (starts == 0) & (not self.started)
            over = ends < n
            if (~over).any():
                k = int(np.flatnonzero(~over)[0])
                new[0][d], new[1][d], new[2][d] = counts[k], best[k], at_start[k]
            if over.any():
                self._emit(rows[1:][starts[over], :d], counts[over], best[over], at_start[over])
                done_first.append(starts[over])
                done_total.append(counts[over].sum(axis=1))
            deeper = (np.concatenate(done_first), np.concatenate(done_total)) if done_first else None
        self.counts[: width + 1], self.best[: width + 1], self.since_start[: width + 1] = (x[: width + 1] for x in new)
        self.path = rows[n, : lengths[-1]].copy()
        self.started = True

    def finish(self) -> None:
        """Close what is open, deepest first; all of it may go on in the next partition."""
        below = 0
        for d in range(len(self.path), 0, -1):
            best = max(int(self.best[d]), below)
            self._emit(self.path[None, :d], self.counts[d][None], np.array([best]), np.array([True]))
            below = int(self.counts[d].sum())
        self.path = np.zeros(0, np.int32)


class StackKernel:
    """The same results with two stacks, terms and accumulators, one row at a time."""

    def __init__(self, tau: int, width: int, weights: int = 1, keep: str = ALL, repair: bool = False):
        self.tau, self.keep, self.repair = tau, keep, repair
        self.terms: list[int] = []
        self.sums: list[np.ndarray] = []
        self.best: list[int] = []
        self.from_start: list[bool] = []
        self.started = False
        self.out = Emitted()
        self.trace: list[tuple[tuple[int, ...], int]] = []

    def _close(self, last: bool) -> None:
        total = int(self.sums[-1].sum())
        good = total >= self.tau and (self.keep == ALL or self.best[-1] < (self.tau if self.keep == MAXIMAL else total))
        opened = self.repair and (last or self.from_start[-1])
        self.trace.append((tuple(self.terms), total))
        if good or opened:
            self.out.add(np.array([self.terms], np.int32), self.sums[-1][None].copy(), np.array([opened]), np.array([self.best[-1]]))
        self.terms.pop()
        done = self.sums.pop()
        self.best.pop()
        self.from_start.pop()
        if self.sums:
            self.sums[-1] = self.sums[-1] + done
            self.best[-1] = max(self.best[-1], total)

    def batch(self, flat: np.ndarray, lengths: np.ndarray, weights: np.ndarray) -> None:
        at = 0
        for length, weight in zip(lengths.tolist(), weights, strict=True):
            row = flat[at : at + length].tolist()
            at += length
            common = 0
            while common < min(length, len(self.terms)) and row[common] == self.terms[common]:
                common += 1
            while len(self.terms) > common:
                self._close(False)
            for term in row[common:]:
                self.terms.append(term)
                self.sums.append(np.zeros(weights.shape[1], np.int64))
                self.best.append(0)
                self.from_start.append(not self.started)
            self.sums[-1] = self.sums[-1] + weight
            self.started = True

    def finish(self) -> None:
        while self.terms:
            self._close(True)


def run(kernel, batches: Iterator[tuple[np.ndarray, np.ndarray, np.ndarray]], cells: int = 1 << 22) -> Iterator[tuple]:
    """Feed batches, cut so that a piece spans at most ``cells`` numbers, and hand on what is emitted."""
    for flat, lengths, weights in batches:
        ends = np.cumsum(lengths)
        step = max(1, cells // max(1, int(lengths.max(initial=1))))
        for a in range(0, len(lengths), step):
            b = min(a + step, len(lengths))
            kernel.batch(flat[ends[a] - lengths[a] : ends[b - 1]], lengths[a:b], weights[a:b])
            if kernel.out.ids:
                yield kernel.out.take()
    kernel.finish()
    if kernel.out.ids:
        yield kernel.out.take()
