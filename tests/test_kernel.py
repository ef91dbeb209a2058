"""The in-memory search against all patterns, for each measure and option."""

import itertools

import numpy as np
import pytest

from contrast.functions.measures import CHI2, CONFIDENCE, FSCORE, INFOGAIN, MEASURES, SUPPDIFF, corner_bound, dual_monotone, harmonic, register
from contrast.plans import kernel
from contrast.plans.boxes import Boxes, suits
from contrast.plans.kernel import Options, Search

SIZES, SYMBOL = [5, 4, 3], [False, False, True]


def instance(seed, rows=14):
    rng = np.random.default_rng(seed)
    codes = np.column_stack([rng.integers(-1 if seed % 3 == 0 else 0, s, rows) for s in SIZES])
    cls = rng.random(rows) < 0.4
    cls[0], cls[1] = True, False
    return codes, cls.astype(int), (~cls).astype(int)


def all_items():
    for a, size in enumerate(SIZES):
        yield [None] + [(a, lo, hi) for lo in range(size) for hi in ([lo + 1] if SYMBOL[a] else range(lo + 1, size + 1)) if SYMBOL[a] or (lo, hi) != (0, size)]


def cover(codes, items):
    held = np.ones(len(codes), bool)
    for a, lo, hi in items:
        held &= (codes[:, a] >= lo) & (codes[:, a] < hi)
    return held


def brute(codes, pos, neg, measure):
    best, p, n = np.zeros(len(pos)), pos.sum(), neg.sum()
    for choice in itertools.product(*all_items()):
        items = [x for x in choice if x]
        held = cover(codes, items)
        a, b = pos[held].sum(), neg[held].sum()
        if items and a and a * n >= b * p:
            best[held & (pos > 0)] = np.maximum(best[held & (pos > 0)], float(measure.values(a, b, p, n)))
    return best


OPTIONS = [Options(), Options(order="given"), Options(merge=False), Options(closed=False), Options(merge=False, closed=False, floor="none", pure_leaves=False)]


@pytest.mark.parametrize("measure", [FSCORE, CHI2, INFOGAIN, SUPPDIFF, CONFIDENCE], ids=lambda m: m.name)
def test_best_of_each_row(measure):
    for seed in range(12):
        codes, pos, neg = instance(seed)
        want, visits = brute(codes, pos, neg, measure), []
        for options in OPTIONS:
            search = Search(codes, pos, neg, SIZES, SYMBOL, measure, pos.sum(), neg.sum(), options=options)
            found = search.run()
            visits.append(found.visited)
            assert np.allclose(search.best * (pos > 0), want)
            assert found.complete
            covered = np.zeros(len(pos), bool)
            for items, score in found.patterns:
                covered |= cover(codes, items)
                assert (search.best[cover(codes, items) & (pos > 0)] <= score).any()
            assert covered[want > 0].all()
        assert visits[0] <= visits[-1]


def test_one_floor_for_all_nodes_loses_answers():
    lost = 0
    for seed in range(60):
        codes, pos, neg = instance(seed)
        search = Search(codes, pos, neg, SIZES, SYMBOL, CHI2, pos.sum(), neg.sum(), options=Options(floor="everywhere", order="given"))
        search.run()
        lost += not np.allclose(search.best * (pos > 0), brute(codes, pos, neg, CHI2))
    assert lost


def test_shards_with_seeds_merge_to_the_answer():
    for seed in range(10):
        codes, pos, neg = instance(seed)
        want, merged = brute(codes, pos, neg, FSCORE), np.zeros(len(pos))
        root = Search(codes, pos, neg, SIZES, SYMBOL, FSCORE, pos.sum(), neg.sum(), options=Options(length=1))
        root.run()
        merged = root.best.copy()
        for items in [(x,) for per in all_items() for x in per if x]:
            shard = Search(codes, pos, neg, SIZES, SYMBOL, FSCORE, pos.sum(), neg.sum(), best=root.best)
            shard.run(items, items[0][0] + 1)
            merged = np.maximum(merged, shard.best)
        assert np.allclose(merged * (pos > 0), want)


def test_stops_on_visits():
    codes, pos, neg = instance(5, rows=40)
    part = Search(codes, pos, neg, SIZES, SYMBOL, FSCORE, pos.sum(), neg.sum(), options=Options(visits=5, floor="none"))
    assert not part.run().complete
    assert (part.best <= brute(codes, pos, neg, FSCORE) + 1e-12).all()


def test_top_k():
    codes, pos, neg = instance(3)
    p, n = pos.sum(), neg.sum()
    scores = []
    for choice in itertools.product(*all_items()):
        items = [x for x in choice if x]
        held = cover(codes, items)
        a, b = pos[held].sum(), neg[held].sum()
        if items and a and a * n >= b * p:
            scores.append(float(FSCORE.values(a, b, p, n)))
    search = Search(codes, pos, neg, SIZES, SYMBOL, FSCORE, p, n, options=Options(top=5, merge=False, closed=False, pure_leaves=False))
    search.run()
    assert np.allclose(sorted(search.tops), sorted(scores)[-5:])


@pytest.mark.parametrize("measure", [FSCORE, CHI2, INFOGAIN, SUPPDIFF], ids=lambda m: m.name)
@pytest.mark.parametrize("parts", [1, 3])
def test_bounded_boxes_have_the_best_of_each_row(measure, parts):
    """The same bests as brute force, and for each row all covers of positives that reach its best."""
    for seed in range(8):
        codes, pos, neg = instance(seed, rows=14 + 4 * seed)
        p, n, want = pos.sum(), neg.sum(), brute(codes, pos, neg, measure)
        found = set()
        for k in range(parts):
            boxes = Boxes(codes, pos, neg, SIZES, SYMBOL, measure, p, n)
            found |= set(boxes.run(k, parts).patterns)
        best = np.zeros(len(pos))
        for items, score in found:
            held = cover(codes, items)
            assert items and score == float(measure.values(pos[held].sum(), neg[held].sum(), p, n))
            best[held & (pos > 0)] = np.maximum(best[held & (pos > 0)], score)
        assert np.allclose(best, want)
        kept = {(cover(codes, x) & (pos > 0)).tobytes() for x, _ in found}
        for choice in itertools.product(*all_items()):
            items = tuple(x for x in choice if x)
            held = cover(codes, items)
            a, b = pos[held].sum(), neg[held].sum()
            if items and a and a * n >= b * p and (float(measure.values(a, b, p, n)) >= want[held & (pos > 0)]).any():
                assert (held & (pos > 0)).tobytes() in kept


@pytest.mark.parametrize("parts", [1, 3])
def test_bounded_boxes_have_the_top(parts):
    """The highest scores of all patterns, equal ones by pattern id."""
    text = lambda items: ";".join(f"{a}:{lo}:{hi}" for a, lo, hi in items)
    options = Options(top=7, merge=False, closed=False, pure_leaves=False)
    assert suits(FSCORE, Options()) and suits(FSCORE, options) and not suits(FSCORE, Options(visits=5)) and not suits(CONFIDENCE, Options())
    for seed in range(10):
        codes, pos, neg = instance(seed, rows=14 + 4 * seed)
        p, n, every = pos.sum(), neg.sum(), []
        for choice in itertools.product(*all_items()):
            items = tuple(x for x in choice if x)
            held = cover(codes, items)
            a, b = pos[held].sum(), neg[held].sum()
            if items and a and a * n >= b * p:
                every.append((-float(FSCORE.values(a, b, p, n)), text(items)))
        got = {(-score, text(items)) for k in range(parts) for items, score in Boxes(codes, pos, neg, SIZES, SYMBOL, FSCORE, p, n, options=options).run(k, parts).patterns}
        assert sorted(every)[:7] == sorted(got)[:7]


def test_bounded_boxes_of_odd_inputs():
    for codes, pos, neg in ((np.zeros((3, 3), int), [1, 1, 1], [0, 0, 0]), (np.full((2, 3), -1), [1, 0], [0, 1]), (np.zeros((0, 3), int), [], []), (np.zeros((2, 3), int), [1, 0], [0, 3])):
        pos, neg = np.array(pos, int), np.array(neg, int)
        for options in (Options(), Options(top=3, merge=False, closed=False, pure_leaves=False)):
            found = Boxes(codes, pos, neg, SIZES, SYMBOL, FSCORE, max(1, int(pos.sum())), int(neg.sum()), options=options).run()
            assert all(items for items, _ in found.patterns)


def test_bounded_boxes_visit_few():
    """Several numbers, where a search node by node visits many times as much."""
    rng = np.random.default_rng(1)
    codes = rng.integers(0, 30, (400, 4))
    pos = ((codes[:, 0] < 12) & (codes[:, 2] > 8) & (rng.random(400) < 0.9)).astype(int)
    args = (codes, pos, 1 - pos, [30] * 4, [False] * 4, FSCORE, int(pos.sum()), int((1 - pos).sum()))
    few = Boxes(*args).run()
    part = Search(*args, options=Options(visits=20 * few.visited)).run()
    assert few.complete and not part.complete


def test_degenerate_inputs():
    for codes, pos, neg in ((np.zeros((3, 3), int), [1, 1, 1], [0, 0, 0]), (np.full((2, 3), -1), [1, 0], [0, 1]), (np.zeros((0, 3), int), [], [])):
        pos, neg = np.array(pos, int), np.array(neg, int)
        Search(codes, pos, neg, SIZES, SYMBOL, FSCORE, max(1, int(pos.sum())), int(neg.sum())).run()


def test_measures():
    assert all(dual_monotone(m) for m in MEASURES.values())
    p, n = 30, 70
    for measure in (FSCORE, CHI2, INFOGAIN, SUPPDIFF):
        for a in range(1, p + 1):
            score = float(measure.values(a, 0, p, n))
            assert abs(measure.floor(score, p, n) * p - a) < 1e-6
            assert all(float(measure.values(a, b, p, n)) <= score + 1e-12 for b in range(0, a * n // p))
    assert corner_bound(CHI2, 10, 5, p, n) >= float(CHI2.values(10, 5, p, n))
    with pytest.raises(ValueError):
        register(type(FSCORE)("bad", lambda a, b, p, n, ln: b - a))


#: Confidence, support and F-score triples that a published run printed, to three digits.
PRINTED = [(1.0, 1.0, 1.0), (1.0, 0.94, 0.969), (0.942, 0.98, 0.961), (0.891, 0.98, 0.933), (0.958, 0.92, 0.939), (0.714, 0.987, 0.829), (0.702, 1.0, 0.825), (0.411, 0.647, 0.503), (0.338, 0.9, 0.492), (0.318, 0.963, 0.478)]


@pytest.mark.parametrize("confidence, support, score", PRINTED)
def test_printed_triples(confidence, support, score):
    assert abs(harmonic(confidence, support) - score) < 0.0015


@pytest.mark.parametrize("measure", [FSCORE, CHI2], ids=lambda m: m.name)
@pytest.mark.parametrize("seed", range(6))
def test_rounds_over_too_many_patterns_to_count_need_no_search_by_node(monkeypatch, measure, seed):
    codes, pos, neg = instance(seed, 40)
    rounds = lambda **few: list(kernel.in_turn(codes, pos, neg, SIZES, SYMBOL, measure, int(neg.sum()), Options(), **few))
    counted = rounds()
    monkeypatch.setattr(kernel, "Search", None)
    assert counted and rounds(dense=0) == counted
