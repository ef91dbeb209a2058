"""The search below one node, in memory: depth first, on the node's compressed rows.

Rows are grouped and weighted, so a node's rows are an index array. For each attribute, base counts and
their running sums give the counts of all intervals at once, and running minima of the rows' best
scores give each interval's own floor. Nothing is shared with other nodes but the rows' best scores,
which only rise: a floor taken over a pattern's own positives is safe for all that extends it.
"""

from __future__ import annotations

import math
import time
from collections.abc import Iterator
from dataclasses import dataclass, field, replace

import numpy as np

from contrast.functions.measures import Measure


@dataclass(frozen=True)
class Options:
    """merge: join pure runs of codes at every node. closed: intervals end on codes with positives.

    uppers: unions of base intervals too. order: 'score' visits the best child first, 'given' in order.
    floor: 'cover' as described, 'none', or 'everywhere' for one floor for all nodes, which loses
    answers. support: a fixed least number of positives. pure_leaves: don't extend what has no negatives.
    visits, seconds: where to stop. length: items of a pattern at most. top: instead of the best of each
    row, so many patterns in all. prune: 'bound' compares a node's bound with the floor's score, 'support'
    its positives with the least support that reaches it; both leave the same nodes. closure: a node goes on
    from the closure of its positives, and positives that were met from no later an attribute are left out.
    """

    merge: bool = True
    closed: bool = True
    uppers: bool = True
    order: str = "score"
    floor: str = "cover"
    support: int = 1
    pure_leaves: bool = True
    visits: int | None = None
    seconds: float | None = None
    length: int | None = None
    top: int | None = None
    prune: str = "bound"
    closure: bool = False


@dataclass
class Found:
    """patterns: items and score. complete: whether nothing was left out for want of visits or time."""

    patterns: list[tuple[tuple[tuple[int, int, int], ...], float]] = field(default_factory=list)
    visited: int = 0
    pruned_floor: int = 0
    pruned_closed: int = 0
    complete: bool = True


class Search:
    """codes: rows by attributes, -1 for none. sizes: codes of each attribute, symbol: which are symbols."""

    def __init__(self, codes: np.ndarray, pos: np.ndarray, neg: np.ndarray, sizes: list[int], symbol: list[bool], measure: Measure, p: int, n: int, best: np.ndarray | None = None, options: Options = Options()):
        self.codes, self.pos, self.neg = codes, pos.astype(np.int64), neg.astype(np.int64)
        self.sizes, self.symbol, self.measure, self.p, self.n, self.options = sizes, symbol, measure, p, n, options
        self.best = np.zeros(len(pos)) if best is None else best.astype(np.float64)
        self.met: dict[bytes, int] = {}
        self.found = Found()
        self.tops: list[float] = []
        self.everywhere = 0.0
        self.until = None if options.seconds is None else time.monotonic() + options.seconds

    def run(self, items: tuple[tuple[int, int, int], ...] = (), first: int = 0) -> Found:
        """Searches all that extends `items` by attributes from `first` on."""
        rows = np.arange(len(self.pos))
        for attr, lo, hi in items:
            rows = rows[(self.codes[rows, attr] >= lo) & (self.codes[rows, attr] < hi)]
        self.visit(rows, items, first)
        self.tidy()
        return self.found

    def spent(self) -> bool:
        limit = self.options.visits
        if (limit is not None and self.found.visited >= limit) or (self.until is not None and time.monotonic() > self.until):
            self.found.complete = False
        return not self.found.complete

    def floors(self, least: np.ndarray) -> np.ndarray:
        """The score that an item's bound must reach."""
        if self.options.top is not None:
            return np.full(len(least), self.tops[0] if len(self.tops) == self.options.top else 0.0)
        if self.options.floor == "none":
            return np.zeros(len(least))
        if self.options.floor == "everywhere":
            return np.full(len(least), self.everywhere)
        return least

    def reaches(self, p: np.ndarray, least: np.ndarray) -> np.ndarray:
        """Whether positive supports may still give what must be reached."""
        floor = self.floors(least)
        if self.options.prune == "support":
            levels, place = np.unique(floor, return_inverse=True)
            needed = np.array([self.measure.floor(float(x), self.p, self.n) * self.p for x in levels])
            return p >= needed[place] * (1 - 1e-12)
        return self.measure.bounds(p, self.p, self.n) >= floor

    def extensions(self, rows: np.ndarray, attr: int) -> tuple[np.ndarray, ...]:
        """lo, hi, positives, negatives and least best score of the attribute's items that cover positives."""
        code = self.codes[rows, attr]
        rows, code = rows[code >= 0], code[code >= 0]
        size = self.sizes[attr]
        pos, neg = np.bincount(code, self.pos[rows], size).astype(np.int64), np.bincount(code, self.neg[rows], size).astype(np.int64)
        least = np.full(size, np.inf)
        some = self.pos[rows] > 0
        np.minimum.at(least, code[some], self.best[rows[some]])
        if self.symbol[attr]:
            at = np.flatnonzero(pos)
            return at, at + 1, pos[at], neg[at], least[at]
        ends = np.flatnonzero(pos) if self.options.closed else np.arange(size)
        before_p, before_q = np.concatenate([[0], np.cumsum(pos)]), np.concatenate([[0], np.cumsum(neg)])
        may_begin = may_end = np.ones(len(ends), bool)
        if self.options.merge and len(ends) > 1:
            # neighbouring ends of a pure run: no negatives from the one to the other, or no positives
            joined = before_q[ends[1:] + 1] == before_q[ends[:-1]]
            if not self.options.closed:
                joined |= before_p[ends[1:] + 1] == before_p[ends[:-1]]
            may_begin, may_end = np.concatenate([[True], ~joined]), np.concatenate([~joined, [True]])
        i, j = np.triu_indices(len(ends)) if self.options.uppers else (np.arange(len(ends)),) * 2
        if self.options.merge and self.options.uppers:
            keep = may_begin[i] & may_end[j]
            i, j = i[keep], j[keep]
        lo, hi = ends[i], ends[j] + 1
        whole = (lo == 0) & (hi == size)
        i, j, lo, hi = i[~whole], j[~whole], lo[~whole], hi[~whole]
        grid = np.minimum.accumulate(np.where(np.arange(len(ends)) >= np.arange(len(ends))[:, None], least[ends], np.inf), axis=1) if len(ends) else np.zeros((0, 0))
        p, q = before_p[hi] - before_p[lo], before_q[hi] - before_q[lo]
        seen = int((pos + neg > 0).sum())
        self.found.pruned_closed += seen * (seen + 1) // 2 - len(lo)
        some = p > 0
        return lo[some], hi[some], p[some], q[some], grid[i, j][some]

    def offer(self, rows: np.ndarray, items, score: float) -> None:
        """Takes a pattern into the lists of the rows that it is best for."""
        top = self.options.top
        if top is not None:
            if len(self.tops) < top or score >= self.tops[0]:
                self.found.patterns.append((items, score))
                self.tops = sorted([*self.tops, score])[-top:]
            return
        held = rows[self.pos[rows] > 0]
        if (score >= self.best[held]).any():
            self.best[held] = np.maximum(self.best[held], score)
            self.found.patterns.append((items, score))
            if len(self.found.patterns) > 20_000:
                self.tidy()

    @staticmethod
    def added(items, item) -> tuple:
        """Items with one more; an item of the same attribute, which a closure may have, is narrowed."""
        rest = [x for x in items if x[0] != item[0]]
        for attr, lo, hi in items:
            if attr == item[0]:
                item = (attr, max(lo, item[1]), min(hi, item[2]))
        return tuple(sorted((*rest, item)))

    def cover(self, items) -> np.ndarray:
        held = np.ones(len(self.pos), bool)
        for attr, lo, hi in items:
            held &= (self.codes[:, attr] >= lo) & (self.codes[:, attr] < hi)
        return held

    def tidy(self) -> None:
        """Keeps the patterns that are still the best for some row, or among the top."""
        top = self.options.top
        if top is not None:
            least = self.tops[0] if len(self.tops) == top else 0.0
            self.found.patterns = [x for x in self.found.patterns if x[1] >= least]
        else:
            self.found.patterns = [(items, score) for items, score in self.found.patterns if (self.best[self.cover(items) & (self.pos > 0)] <= score).any()]

    def closed(self, rows: np.ndarray, items) -> tuple[np.ndarray, tuple]:
        """The rows of the closure of these rows' positives, and its items: the spans of their codes."""
        own = self.codes[rows[self.pos[rows] > 0]]
        lo, hi = own.min(axis=0), own.max(axis=0) + 1
        spans = [(a, int(x), int(y)) for a, (x, y) in enumerate(zip(lo, hi)) if x >= 0 and (y == x + 1 if self.symbol[a] else (x, y) != (0, self.sizes[a]))]
        for attr, a, b in spans:
            rows = rows[(self.codes[rows, attr] >= a) & (self.codes[rows, attr] < b)]
        return rows, tuple(spans)

    def visit(self, rows: np.ndarray, items, first: int) -> None:
        children = []
        if self.options.closure and len(items):
            rows, closure = self.closed(rows, items)
            key = rows[self.pos[rows] > 0].tobytes()
            if self.met.get(key, len(self.sizes)) <= first:
                self.found.pruned_closed += 1
                return
            self.met[key] = first
            p, q = int(self.pos[rows].sum()), int(self.neg[rows].sum())
            if p * self.n >= q * self.p:
                self.offer(rows, closure, float(self.measure.values(p, q, self.p, self.n)))
            items = closure
        for attr in range(first, len(self.sizes)):
            lo, hi, p, q, least = self.extensions(rows, attr)
            keep = self.reaches(p, least) & (p >= self.options.support)
            self.found.visited += int(keep.sum())
            self.found.pruned_floor += int((~keep).sum())
            lo, hi, p, q, least = lo[keep], hi[keep], p[keep], q[keep], least[keep]
            score = self.measure.values(p, q, self.p, self.n)
            children += [(-s, attr, a, b, x, y) for s, a, b, x, y in zip(score.tolist(), lo.tolist(), hi.tolist(), p.tolist(), q.tolist())]
        if self.options.order == "score":
            children.sort()
        for down, attr, lo, hi, p, q in children:
            if p * self.n >= q * self.p:
                held = rows[(self.codes[rows, attr] >= lo) & (self.codes[rows, attr] < hi)]
                self.offer(held, self.added(items, (attr, lo, hi)), -down)
                if self.options.floor == "everywhere":  # what one floor for all nodes would be raised to
                    self.everywhere = max(self.everywhere, self.best[held[self.pos[held] > 0]].min(initial=np.inf))
        if self.options.length is not None and len(items) + 1 >= self.options.length:
            return
        for _, attr, lo, hi, p, q in children:
            if self.spent():
                return
            if attr + 1 == len(self.sizes) or (q == 0 and self.options.pure_leaves and self.measure.strict):
                continue
            held = rows[(self.codes[rows, attr] >= lo) & (self.codes[rows, attr] < hi)]
            if not self.reaches(np.array([p]), np.array([self.best[held[self.pos[held] > 0]].min()]))[0]:
                self.found.pruned_floor += 1
                continue
            self.visit(held, self.added(items, (attr, lo, hi)), attr + 1)


#: Patterns in all up to which they are counted at once, in arrays, instead of searched for.
DENSE = 4_000_000


class Dense:
    """Counts of all patterns at once: an axis for each attribute, with its items and, last, with none of them.

    A histogram of the rows' codes is summed up along each axis, and an interval is a difference of two sums.
    """

    def __init__(self, codes: np.ndarray, sizes: list[int], symbol: list[bool]):
        self.sizes, self.symbol = sizes, symbol
        ends = [(np.arange(s), np.arange(1, s + 1)) if one else tuple(x[:, ~((x[0] == 0) & (x[1] == s))] for x in [np.stack(np.triu_indices(s)) + [[0], [1]]])[0] for s, one in zip(sizes, symbol)]
        self.lo, self.hi = [e[0] for e in ends], [e[1] for e in ends]
        self.cells = [s + 1 for s in sizes]  # the last cell is for rows without a code
        self.at = np.ravel_multi_index(tuple(np.where(codes[:, k] < 0, s, codes[:, k]) for k, s in enumerate(sizes)), self.cells) if len(sizes) else np.zeros(len(codes), np.int64)

    @staticmethod
    def patterns(sizes: list[int], symbol: list[bool]) -> int:
        return math.prod((s if one else s * (s + 1) // 2) + 1 for s, one in zip(sizes, symbol))

    def counts(self, weights: np.ndarray) -> np.ndarray:
        cube = np.zeros(math.prod(self.cells), np.int64)
        np.add.at(cube, self.at, weights)
        cube = cube.reshape(self.cells)
        for k, (lo, hi) in enumerate(zip(self.lo, self.hi)):
            sums = np.cumsum(cube, axis=k)
            sums = np.concatenate([np.zeros_like(sums.take([0], k)), sums], axis=k)
            cube = np.concatenate([sums.take(hi, k) - sums.take(lo, k), sums.take([-1], k)], axis=k)
        return cube

    def best(self, scores: np.ndarray) -> np.ndarray:
        """For each cell of codes the best score of all patterns that hold it."""
        for k, (size, one) in enumerate(zip(self.sizes, self.symbol)):
            scores = np.moveaxis(scores, k, 0)
            if one:
                cells = np.maximum(scores, scores[-1])
            else:
                spans = np.full((size, size + 1, *scores.shape[1:]), -np.inf)
                spans[self.lo[k], self.hi[k]] = scores[:-1]
                if size:
                    spans[0, size] = scores[-1]
                for width in range(size - 1, 0, -1):
                    lo = np.arange(size - width + 1)
                    spans[lo[1:], lo[1:] + width] = np.maximum(spans[lo[1:], lo[1:] + width], spans[lo[1:] - 1, lo[1:] + width])
                    spans[lo[:-1], lo[:-1] + width] = np.maximum(spans[lo[:-1], lo[:-1] + width], spans[lo[:-1], lo[:-1] + width + 1])
                cells = np.concatenate([spans[np.arange(size), np.arange(size) + 1], scores[-1:]])
            scores = np.moveaxis(cells, 0, k)
        return scores

    def least(self, cells: np.ndarray) -> np.ndarray:
        """For each pattern the least value of the cells that it holds."""
        for k, (size, one) in enumerate(zip(self.sizes, self.symbol)):
            cells = np.moveaxis(cells, k, 0)
            if one:
                spans = cells[:-1]
            else:
                table = np.full((size, size + 1, *cells.shape[1:]), np.inf)
                at = np.arange(size)
                table[at, at + 1] = cells[:-1]
                for width in range(2, size + 1):
                    lo = np.arange(size - width + 1)
                    table[lo, lo + width] = np.minimum(table[lo, lo + width - 1], table[lo + 1, lo + width])
                spans = table[self.lo[k], self.hi[k]]
            cells = np.moveaxis(np.concatenate([spans, cells.min(axis=0, keepdims=True)]), 0, k)
        return cells

    def items(self, place: int, shape: tuple[int, ...]) -> tuple:
        found = np.unravel_index(place, shape)
        return tuple((k, int(self.lo[k][x]), int(self.hi[k][x])) for k, x in enumerate(found) if x < len(self.lo[k]))


def in_turn(codes: np.ndarray, pos: np.ndarray, neg: np.ndarray, sizes: list[int], symbol: list[bool], measure: Measure, n: int, options: Options, rounds: int | None = None, dense: int = DENSE) -> Iterator[tuple[tuple, float, int]]:
    """The best of all patterns, then the best for the positives that it leaves, and so on: items, score, positives left.

    Equal scores go by pattern id. Ends when no positives are left, no pattern is found or nothing is covered.
    Without limits of its own and with few patterns in all, each round counts them all; with more it goes by branch and bound, else it searches.
    """
    from contrast.plans.boxes import Boxes, suits

    options, pos, before = replace(options, top=1, merge=False, closed=False, closure=False, pure_leaves=False), pos.astype(np.int64), None
    plain = options.uppers and options.support <= 1 and options.length is options.visits is options.seconds is None
    every = Dense(codes, sizes, symbol) if plain and Dense.patterns(sizes, symbol) <= dense else None
    b = None if every is None else every.counts(neg)
    while (p := int(pos.sum())) and p != before and rounds != 0:
        if every is None:
            some = pos + neg > 0
            way = Boxes if suits(measure, options) else Search
            found = way(codes[some], pos[some], neg[some], sizes, symbol, measure, p, n, options=options).run().patterns
        else:
            a = every.counts(pos)
            fits = (a > 0) & (a * n >= b * p)
            fits.flat[-1] = False  # the pattern without items
            places = np.flatnonzero(fits)
            scores = measure.values(a.flat[places], b.flat[places], p, n)
            found = [(every.items(int(k), a.shape), float(scores.max())) for k in places[scores == scores.max()]] if len(places) else []
        if not found:
            return
        items, score = min(found, key=lambda x: (-x[1], ";".join(f"{k}:{lo}:{hi}" for k, lo, hi in x[0])))
        yield items, score, p
        held = np.ones(len(pos), bool)
        for k, lo, hi in items:
            held &= (codes[:, k] >= lo) & (codes[:, k] < hi)
        pos, before, rounds = np.where(held, 0, pos), p, rounds if rounds is None else rounds - 1
