"""Branch and bound over the ends of all intervals at once, for tables with too many patterns to visit.

A node is a set of boxes: for each number, ranges where an interval may begin and end. Its widest box has all
positives that any box of the node can have, its narrowest box the negatives that each must have. A box that
reaches a score can do without few positives only, and that moves the ranges, widens the narrowest box and
raises what must be reached, until nothing moves. Symbols, and numbers that some rows lack, are settled first.
"""

from __future__ import annotations

from collections import deque
from collections.abc import Iterator
from heapq import heappush, heappushpop, nsmallest

import numpy as np

from contrast.functions.measures import FSCORE, Measure
from contrast.plans.kernel import Found, Options

#: Interval ends that an ascent tries at an attribute, and rows from which ascents set out, at most: they only give scores to begin with.
TRIED_ENDS, ASCENTS = 400, 200
TINY = 1e-12


def suits(measure: Measure, options: Options) -> bool:
    """Whether options ask for a whole answer, or the top ones of all patterns, in the plain way."""
    plain = options.uppers and options.support <= 1 and options.length is options.visits is options.seconds is None
    ways = (options.order, options.floor, options.prune, options.closure) == ("score", "cover", "bound", False)
    pruned = options.merge and options.closed and options.pure_leaves
    return plain and ways and measure.strict and (pruned if options.top is None else not (options.merge or options.closed or options.pure_leaves))


def least_positives(measure: Measure, score: float, q: float, most: int, p: int, n: int) -> int:
    """The fewest positives, up to `most`, with which q negatives still reach a score and are associated; most + 1 if none."""
    low = -(-int(q) * p // n) if n else 0
    if measure is FSCORE:
        return max(low, int(np.ceil(score * (p + q) / (2 - score) - 1e-6)))
    if most < low or float(measure.values(most, q, p, n)) < score - TINY:
        return most + 1
    high = most
    while low < high:
        middle = (low + high) // 2
        low, high = (low, middle) if float(measure.values(middle, q, p, n)) >= score - TINY else (middle + 1, high)
    return low


class Boxes:
    """The arguments are those of kernel.Search."""

    def __init__(self, codes: np.ndarray, pos: np.ndarray, neg: np.ndarray, sizes: list[int], symbol: list[bool], measure: Measure, p: int, n: int, best: np.ndarray | None = None, options: Options = Options()):
        self.codes, self.pos, self.neg = codes, pos.astype(np.int64), neg.astype(np.int64)
        self.sizes, self.symbol, self.measure, self.p, self.n, self.top = sizes, symbol, measure, p, n, options.top
        self.best = np.zeros(len(pos)) if best is None else best.astype(np.float64)
        self.found, self.least, self.heap = Found(), 0.0, []

    def run(self, part: int = 0, parts: int = 1) -> Found:
        """Searches the part-th of so many parts of all boxes; each begins with the scores that ascents find."""
        self.ascend()
        nodes = deque(self.roots())
        while nodes and len(nodes) < 8 * parts and parts > 1:
            nodes.extend(self.split(nodes.popleft()))
        if part:
            self.found.visited = self.found.pruned_floor = 0
        nodes = list(nodes)[part::parts]
        while nodes:
            nodes.extend(self.split(nodes.pop()))
        self.tidy()
        return self.found

    # Scores to begin with

    def score(self, p, q) -> float:
        return float(self.measure.values(p, q, self.p, self.n))

    def held(self, box: list, but: int | None = None) -> np.ndarray:
        held = np.ones(len(self.pos), bool)
        for a, item in enumerate(box):
            if item and a != but:
                held &= (self.codes[:, a] >= item[0]) & (self.codes[:, a] < item[1])
        return held

    def steps(self, box: list, a: int, row: int | None) -> tuple[np.ndarray, np.ndarray, np.ndarray]:
        """lo, hi and score of items of one attribute beside the box's other items; lo is -1 for none. Not associated: minus infinity."""
        held, size = self.held(box, a), self.sizes[a]
        p, q = self.pos[held], self.neg[held]
        code = self.codes[held, a]
        some = code >= 0
        x, y = (np.concatenate([[0], np.cumsum(np.bincount(code[some], w[some], size))]) for w in (p, q))
        if self.symbol[a]:
            lo, hi = np.arange(size), np.arange(1, size + 1)
        else:
            ends = np.flatnonzero(np.diff(x))
            ends = ends[np.unique(np.linspace(0, len(ends) - 1, min(len(ends), TRIED_ENDS)).astype(int))] if len(ends) else ends
            i, j = np.triu_indices(len(ends))
            lo, hi = ends[i], ends[j] + 1
            inner = (lo > 0) | (hi < size)
            lo, hi = lo[inner], hi[inner]
        if row is not None:
            holds = (lo <= self.codes[row, a]) & (self.codes[row, a] < hi)
            lo, hi = lo[holds], hi[holds]
        lo, hi, x, y = np.append(lo, -1), np.append(hi, -1), np.append(x[hi] - x[lo], p.sum()), np.append(y[hi] - y[lo], q.sum())
        fits = (x > 0) & (x * self.n >= y * self.p)
        return lo, hi, np.where(fits, self.measure.values(np.where(fits, x, 1), np.where(fits, y, 0), self.p, self.n), -np.inf)

    def climbed(self, row: int | None) -> tuple[list, float]:
        """A box that no change of one item betters, among those that hold a row, if one is given."""
        box, score = [None] * len(self.sizes), -np.inf
        while True:
            tried = [(float(s.max()), a, int(lo[s.argmax()]), int(hi[s.argmax()])) for a in range(len(box)) for lo, hi, s in [self.steps(box, a, row)]]
            most, a, lo, hi = max(tried, default=(-np.inf, 0, 0, 0))
            if most <= score + TINY:
                return box, score
            box[a], score = (None if lo < 0 else (lo, hi)), most

    def ascend(self) -> None:
        if self.top is not None:
            box, _ = self.climbed(None)
            near = [s[[(None if u < 0 else (int(u), int(v))) != box[a] for u, v in zip(lo, hi)]] for a in range(len(box)) for lo, hi, s in [self.steps(box, a, None)]]
            near = np.sort(np.concatenate(near))[::-1] if near else np.zeros(0)
            # one of them may have no items and isn't a pattern
            self.least = float(near[self.top]) if len(near) > self.top and near[self.top] > 0 else 0.0
            return
        tried = np.zeros(len(self.pos), bool)
        for k in range(ASCENTS):
            open_ = np.flatnonzero((self.pos > 0) & (self.best <= 0) & ~tried)
            if not len(open_):
                return
            row = None if k == 0 else int(open_[0])
            box, score = self.climbed(row)
            if row is not None:
                tried[row] = True
            if np.isfinite(score) and any(box):
                self.offer(np.flatnonzero(self.held(box) & (self.pos > 0)), tuple((a, *x) for a, x in enumerate(box) if x), score)

    def offer(self, rows: np.ndarray, items: tuple, score: float) -> None:
        """Takes a pattern into the lists of the positive rows that it is best for."""
        if (score >= self.best[rows]).any():
            self.best[rows] = np.maximum(self.best[rows], score)
            self.found.patterns.append((items, score))
            if len(self.found.patterns) > 20_000:
                self.tidy()

    def tidy(self) -> None:
        if self.top is not None:
            self.found.patterns = [x for x in self.found.patterns if x[1] >= self.floor()]
            return
        kept = []
        for items, score in dict.fromkeys(self.found.patterns):
            box = [None] * len(self.sizes)
            for a, lo, hi in items:
                box[a] = (lo, hi)
            if (self.best[self.held(box) & (self.pos > 0)] <= score).any():
                kept.append((items, score))
        self.found.patterns = kept

    def floor(self) -> float:
        """What the top ones must reach."""
        return max(self.least, self.heap[0] if len(self.heap) == self.top else 0.0)

    # Nodes

    def roots(self) -> Iterator[tuple]:
        """Nodes with the symbols settled, and for numbers that rows lack, whether there is an item: fixed items, free numbers and rows."""
        first = [a for a, one in enumerate(self.symbol) if one or (self.codes[:, a] < 0).any()]
        waiting = [(0, (), (), np.flatnonzero(self.pos > 0), np.flatnonzero(self.neg > 0))]
        while waiting:
            k, fixed, partial, pos, neg = waiting.pop()
            p = int(self.pos[pos].sum())
            floor = self.floor() if self.top is not None else self.best[pos].min(initial=np.inf)
            if not p or self.score(p, 0) < floor - TINY:
                continue
            if k == len(first):
                free = [a for a, one in enumerate(self.symbol) if not one and (a not in first or a in partial)]
                yield fixed, free, np.array([a in partial for a in free], bool), pos, neg, pos, *(np.array([f(self.sizes[a]) for a in free], np.int64) for f in (lambda s: 0, lambda s: s - 1, lambda s: 1, lambda s: s))
                continue
            a = first[k]
            waiting.append((k + 1, fixed, partial, pos, neg))
            if self.symbol[a]:
                for v in np.unique(self.codes[pos, a]):
                    if v >= 0:
                        waiting.append((k + 1, (*fixed, (a, int(v), int(v) + 1)), partial, pos[self.codes[pos, a] == v], neg[self.codes[neg, a] == v]))
            else:
                waiting.append((k + 1, fixed, (*partial, a), pos[self.codes[pos, a] >= 0], neg[self.codes[neg, a] >= 0]))

    def split(self, node: tuple) -> list[tuple]:
        """The node's two halves, or nothing, if it holds no answer or has been taken whole."""
        fixed, free, partial, pos, neg, open_, la, lb, ha, hb = node
        self.found.visited += 1
        lb, ha, sizes = lb.copy(), ha.copy(), np.array([self.sizes[a] for a in free], np.int64)
        c, w = self.codes[pos][:, free], self.pos[pos]
        if not len(pos):
            return []
        if self.top is None and free:  # intervals end on codes with positives
            la, hb = np.maximum(la, c.min(axis=0)), np.minimum(hb, c.max(axis=0) + 1)
        if (la > lb).any() or (ha > hb).any():
            return []
        d = self.codes[neg][:, free]
        inside = ((d >= la) & (d < hb)).all(axis=1)
        neg, d = neg[inside], d[inside]
        v = self.neg[neg]
        p, q, every = int(w.sum()), int(v.sum()), []
        whole = (la == 0) & (hb == sizes)
        if self.top is None and p * self.n >= q * self.p and not (whole & partial).any() and (fixed or not whole.all()):
            self.offer(pos, tuple(sorted((*fixed, *((a, int(x), int(y)) for a, x, y, z in zip(free, la, hb, whole) if not z)))), self.score(p, q))
        for k, size in enumerate(sizes):
            every.append(np.cumsum(np.bincount(c[:, k], w, size)).astype(np.int64))
        must, row = 0, None
        while True:
            if self.top is None:
                if not len(open_):
                    self.found.pruned_floor += 1
                    return []
                row = int(open_[self.best[open_].argmin()])
                floor = self.best[row]
            else:
                floor = self.floor()
            spare = p - least_positives(self.measure, floor, must, p, self.p, self.n)
            if spare < 0:
                self.found.pruned_floor += 1
                return []
            for k, to in enumerate(every):
                lb[k] = min(lb[k], np.searchsorted(to, spare, "right"))
                ha[k] = max(ha[k], np.searchsorted(to, to[-1] - spare, "left") + 1)
            if (la > lb).any() or (ha > hb).any():
                self.found.pruned_floor += 1
                return []
            if (now := int(v[((d >= lb) & (d < ha)).all(axis=1)].sum())) > must:
                must = now
                continue
            if self.top is not None:
                break
            # the row that asks for least may be in none of the boxes that reach its own best
            own = self.codes[row, free]
            lo, hi = np.minimum(lb, own), np.maximum(ha, own + 1)
            with_row = int(v[((d >= lo) & (d < hi)).all(axis=1)].sum())
            if p >= least_positives(self.measure, floor, with_row, p, self.p, self.n):
                break
            open_ = open_[open_ != row]
        if self.top is not None and self.take_block(fixed, free, partial, c, w, p, q, must, la, lb, ha, hb):
            return []
        room = np.concatenate([lb - la, hb - ha])
        if not room.any():
            return []
        out = np.concatenate([d < lb, d >= ha], axis=1)
        alone = out.sum(axis=1) == 1
        gain = np.where(room > 0, v[alone] @ out[alone] + 0.05 * (v @ out) + 1e-6, -1.0)
        k = None
        if row is not None:
            own = self.codes[row, free]
            apart = np.concatenate([own < lb, own >= ha]) & (room > 0)
            if apart.any():  # first with that row, then without
                k = int(np.where(apart, gain, -1.0).argmax())
                at = int(own[k % len(free)]) + (k >= len(free))
        if k is None:
            k = int(gain.argmax())
            to = every[k % len(free)]
            at = int(np.searchsorted(to, spare / 2, "right")) if k < len(free) else int(np.searchsorted(to, to[-1] - spare / 2, "left")) + 1
        if k < len(free):
            at = min(max(at, la[k]), lb[k] - 1)
            near, far = lb.copy(), la.copy()
            near[k], far[k] = at, at + 1
            mine, theirs, rows = c[:, k] > at, d[:, k] > at, self.codes[open_, free[k]] > at
            return [(fixed, free, partial, pos[mine], neg[theirs], open_[rows], far, lb, ha, hb), (fixed, free, partial, pos, neg, open_, la, near, ha, hb)]
        k -= len(free)
        at = max(min(at, hb[k]), ha[k] + 1)
        near, far = ha.copy(), hb.copy()
        near[k], far[k] = at, at - 1
        mine, theirs, rows = c[:, k] < at - 1, d[:, k] < at - 1, self.codes[open_, free[k]] < at - 1
        return [(fixed, free, partial, pos[mine], neg[theirs], open_[rows], la, lb, ha, far), (fixed, free, partial, pos, neg, open_, la, lb, near, hb)]

    def take_block(self, fixed, free, partial, c, w, p, q, must, la, lb, ha, hb) -> bool:
        """Takes a node's first patterns by id into the top ones, if all its boxes have the same counts."""
        if must != q or (la != lb).any() | (ha != hb).any() and int(w[((c >= lb) & (c < ha)).all(axis=1)].sum()) != p:
            return False
        if p * self.n < q * self.p:
            return True
        score, held = self.score(p, q), {a: (k, lo, hi) for k, (a, lo, hi) in enumerate(fixed)}
        if score < self.floor():
            return True
        tails = [("", ())]  # the first ones of all ends of a pattern's id
        for a in range(len(self.sizes) - 1, -1, -1):
            if a in held:
                own, none = [held[a][1:]], False
            elif a in free:
                k = free.index(a)
                size = self.sizes[a]
                own = [(lo, hi) for lo in range(la[k], lb[k] + 1) for hi in range(max(lo + 1, ha[k]), hb[k] + 1) if (lo, hi) != (0, size)]
                none = la[k] == 0 and hb[k] == size and not partial[k]
            else:
                own, none = [], True
            made = ((f"{a}:{lo}:{hi}" + (";" + text if text else ""), ((a, int(lo), int(hi)), *items)) for lo, hi in own for text, items in tails)
            tails = nsmallest(self.top + 1, [*made, *(tails if none else [])])
        for _, items in [x for x in tails if x[1]][: self.top]:
            self.found.patterns.append((items, score))
            (heappushpop if len(self.heap) == self.top else heappush)(self.heap, score)
        if len(self.found.patterns) > 20_000:
            self.tidy()
        return True
