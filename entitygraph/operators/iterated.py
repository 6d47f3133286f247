"""The entropy-iterated baseline over one sample as a search in memory: tokens and records are numbers, and every round of every run works on whole arrays.

A sample has at most some tens of thousands of records whatever the tables' size, so its runs fit a task; the pairs that any run meets have their token-by-token edit
distances computed once. Results are those of the rounds as joins (``experiment.baseline_rounds``), to the last place."""

from __future__ import annotations

from collections.abc import Iterator
from dataclasses import dataclass

import numpy as np

from entitygraph.functions.sql import rounded

#: Reductions of the scoring matrix that the search knows.
MEASURES = ("both", "rows", "cols", "shorter", "monge_elkan")
#: New pairs whose cells are compared at once.
CHUNK = 20_000


def components(n: int, a: np.ndarray, b: np.ndarray) -> np.ndarray:
    """Of each of n nodes the least node that edges reach."""
    label = np.arange(n)
    while True:
        x, y = label[a], label[b]
        apart = x != y
        if not apart.any():
            return label
        a, b, x, y = a[apart], b[apart], x[apart], y[apart]
        np.minimum.at(label, np.maximum(x, y), np.minimum(x, y))
        while (label[label] != label).any():
            label = label[label]


def edit_distances(chars: np.ndarray, length: np.ndarray, u: np.ndarray, v: np.ndarray) -> np.ndarray:
    """Edit distances of words u[i] and v[i]; words of the same two lengths go through the table of distances together."""
    out = np.zeros(len(u), np.int64)
    kind = length[u] * (chars.shape[1] + 1) + length[v]
    order = np.argsort(kind, kind="stable")
    stops = np.append(np.flatnonzero(np.diff(kind[order])) + 1, len(order)) if len(order) else []
    small = np.uint8 if chars.shape[1] < 255 else np.int32
    at = 0
    for stop in stops:
        rows, at = order[at:stop], stop
        x, y = (np.ascontiguousarray(chars[w[rows], : length[w[rows[0]]]].T) for w in (u, v))
        line = [np.full(len(rows), j, small) for j in range(len(y) + 1)]
        for i, c in enumerate(x, 1):
            last, line[0] = line[0], np.full(len(rows), i, small)
            for j, d in enumerate(y, 1):
                best = np.minimum(np.minimum(line[j], line[j - 1]) + small(1), last + (c != d).astype(small))
                last, line[j] = line[j], best
        out[rows] = line[-1]
    return out


def six_places(x: np.ndarray) -> np.ndarray:
    """Half up to nine places on the shortest decimal form, then to six, as the scores of the joins are rounded."""
    wide = x * 1e9
    nine = np.floor(wide + 0.5).astype(np.int64)
    for i in np.flatnonzero(np.abs(wide - np.floor(wide) - 0.5) < 1e-4):
        nine[i] = round(rounded(float(x[i]), 9) * 1e9)
    return (nine + 500) // 1000 / 1e6


@dataclass
class Round:
    label: np.ndarray
    quality: np.ndarray
    comparisons: int
    cells: int


class Sample:
    """Records in the order of their ids, their words, and the distances of the pairs met so far."""

    def __init__(self, bodies: list[str], beta: int = 6, sigma: int = 7, bounds: str = "inclusive", measure: str = "both", max_tokens: int | None = None):
        words = [[t for t in (x or "").split(" ") if t] for x in bodies]
        number: dict[str, int] = {}
        self.n, self.width = len(words), max([1, *map(len, words)])
        self.token = np.array([number.setdefault(t, len(number)) for x in words for t in x], np.int64)
        size = np.array([len(x) for x in words], np.int64)
        self.record = np.repeat(np.arange(self.n), size)
        self.slot = np.arange(len(self.token)) - np.repeat(np.cumsum(size) - size, size)
        self.at = np.full((self.width, self.n), -1)
        self.at[self.slot, self.record] = self.token
        names = list(number)
        self.length = np.array([len(t) for t in names], np.int64)
        longest = int(self.length.max()) if names else 1
        self.chars = np.array(names or [""], f"U{longest}").view(np.uint32).reshape(-1, longest)
        # a similarity by its number: distance and greater length
        base = longest + 1
        self.base, distance, greater = base, *np.divmod(np.arange(base * base), base)
        self.value = 1.0 - distance / np.maximum(greater, 1)
        self.known = np.empty(0, np.int64)
        self.place = np.empty(0, np.int64)
        self.codes = np.empty((self.width, self.width, 0), np.uint16 if base * base < 1 << 16 else np.uint32)
        self.kept_limit = sigma if bounds == "inclusive" else sigma + 1
        self.block_limit = beta + 1 if bounds == "inclusive" else beta
        self.measure, self.max_tokens = measure, max_tokens

    def _compare(self, pairs: np.ndarray) -> None:
        """Adds the cells of pairs (a * n + b) that are new."""
        fresh = pairs[~np.isin(pairs, self.known, assume_unique=True)]
        if not len(fresh):
            return
        parts = [self.codes]
        for lo in range(0, len(fresh), CHUNK):
            a, b = np.divmod(fresh[lo : lo + CHUNK], self.n)
            u, v = np.broadcast_arrays(self.at[:, None, a], self.at[None, :, b])
            there = (u >= 0) & (v >= 0)
            u, v = u[there], v[there]
            each, back = np.unique(np.minimum(u, v) * len(self.length) + np.maximum(u, v), return_inverse=True)
            u, v = np.divmod(each, len(self.length))
            code = edit_distances(self.chars, self.length, u, v) * self.base + np.maximum(self.length[u], self.length[v])
            cells = np.zeros(there.shape, self.codes.dtype)
            cells[there] = code[back].astype(self.codes.dtype)
            parts.append(cells)
        known = np.append(self.known, fresh)
        place = np.append(self.place, np.arange(len(self.known), len(known)))
        order = np.argsort(known)
        self.known, self.place, self.codes = known[order], place[order], np.concatenate(parts, axis=2)

    def _scores(self, pairs: np.ndarray, kept: np.ndarray) -> tuple[np.ndarray, np.ndarray]:
        """Score and matrix cells of pairs. kept: of each slot and record, whether its word is in the list."""
        self._compare(pairs)
        where = self.place[np.searchsorted(self.known, pairs)]
        out, cells = np.zeros(len(pairs)), np.zeros(len(pairs), np.int64)
        for lo in range(0, len(pairs), CHUNK):
            some = slice(lo, lo + CHUNK)
            a, b = np.divmod(pairs[some], self.n)
            ka, kb, at = kept[:, a], kept[:, b], where[some]
            rows, cols = (np.zeros((self.width, len(a))) for _ in range(2))
            for i in range(self.width):
                if not ka[i].any():
                    continue
                for j in range(self.width):
                    both = ka[i] & kb[j]
                    x = np.flatnonzero(both)
                    if len(x):
                        s = self.value[self.codes[i, j, at[x]]]
                        rows[i, x] = np.maximum(rows[i, x], s)
                        cols[j, x] = np.maximum(cols[j, x], s)
            by_row, by_col = np.zeros(len(a)), np.zeros(len(a))
            for k in range(self.width):  # in the order of the lists, one after the other
                by_row += rows[k]
                by_col += cols[k]
            na, nb = ka.sum(axis=0), kb.sum(axis=0)
            if self.measure == "both":
                score = (by_row + by_col) / (na + nb)
            elif self.measure == "cols":
                score = by_col / nb
            elif self.measure == "shorter":
                score = np.where(na <= nb, by_row / na, by_col / nb)
            else:
                score = by_row / na
            out[some], cells[some] = six_places(score), na * nb
        return out, cells

    def round(self, left: np.ndarray, mu: float) -> Round:
        """Blocks, scores and closes the records that are left (a mask), and judges the clusters: label and quality of every record that is left."""
        held = left[self.record]
        token, record = self.token[held], self.record[held]
        count = np.bincount(token, minlength=len(self.length))
        rare = np.unique(token[count[token] < min(self.block_limit, self.kept_limit)] * self.n + record[count[token] < min(self.block_limit, self.kept_limit)])
        t, r = np.divmod(rare, self.n)
        found = [np.empty(0, np.int64)]
        for step in range(1, self.block_limit):
            same = t[step:] == t[:-step]
            found.append((r[:-step] * self.n + r[step:])[same])
        pairs = np.unique(np.concatenate(found))
        kept = np.zeros(self.at.shape, bool)
        kept[self.slot[held], record] = count[token] < self.kept_limit
        if self.max_tokens:
            kept &= np.cumsum(kept, axis=0) <= self.max_tokens
        score, cells = self._scores(pairs, kept)
        a, b = np.divmod(pairs[score >= mu], self.n)
        label = components(self.n, a, b)
        quality = self._quality(label, left, token, record)
        return Round(label, quality, len(pairs), int(cells.sum()))

    def _quality(self, label: np.ndarray, left: np.ndarray, token: np.ndarray, record: np.ndarray) -> np.ndarray:
        """``entropy_quality`` of each record's cluster."""
        size = np.bincount(label[left], minlength=self.n)
        several = size[label[record]] > 1
        each, c = np.unique(label[record[several]] * len(self.length) + token[several], return_counts=True)
        of = each // max(1, len(self.length))
        t = np.bincount(of, c, self.n)
        clogc = np.bincount(of, c * np.log2(c), self.n)
        judged = (size > 1) & (t > 0)
        n, t, clogc = size[judged], t[judged], clogc[judged]
        h, low, high = np.log2(t) - clogc / t, np.log2(t / n), np.log2(t)
        out = np.ones(self.n)
        out[judged] = np.floor(np.clip(1 - (h - low) / (high - low), 0.0, 1.0) * 1e6 + 0.5) / 1e6
        return out[label]

    def runs(self, mu: float, epsilons: list[float], step: float = 0.1) -> Iterator[tuple[float, np.ndarray, int, int, int]]:
        """epsilon, the least record of each record's cluster, rounds, comparisons, matrix cells. The first round is the same for all."""
        first = self.round(np.ones(self.n, bool), mu)
        for epsilon in epsilons:
            left, now, m, one = np.ones(self.n, bool), mu, np.arange(self.n), first
            rounds = comparisons = cells = 0
            while left.any():
                if rounds:
                    one = self.round(left, now)
                rounds, comparisons, cells = rounds + 1, comparisons + one.comparisons, cells + one.cells
                now = round(now + step, 6)
                out = left & ((one.quality >= epsilon) | (now >= 1))
                m[out] = one.label[out]
                left = left & ~out
            yield epsilon, m, rounds, comparisons, cells


def pair_counts(cluster: np.ndarray, truth: np.ndarray) -> tuple[int, int, int]:
    """Pairs in one cluster and one true group, in one cluster, in one true group."""
    pairs = lambda x: int((x * (x - 1) // 2).sum())
    both = np.unique(cluster * (int(truth.max(initial=0)) + 1) + truth, return_counts=True)[1]
    return pairs(both), pairs(np.bincount(cluster)), pairs(np.bincount(truth))
