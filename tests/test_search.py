import itertools
import random
from dataclasses import replace

import numpy as np
import pytest

from tagroute.baselines import METHODS, local
from tagroute.distance.arrays import FAR, SpotRows
from tagroute.query import QuerySpec, search
from tagroute.query.search import Arrays
from tagroute.registry import Data

#: Scores, distances, rating sums and POIs in order of visit, from an independent brute force (start 1000, sf0.01).
KNOWN = {
    ((3, 5, 7, 11), 0.2): [(15.446784, 821, 271, [86, 21, 68, 39]), (15.149708, 579, 239, [67, 86, 70, 21]), (14.326316, 767, 252, [86, 51, 94, 39]), (14.263158, 849, 261, [86, 70, 21, 39])],
    ((3, 5, 7, 11), 0.6): [(-6.794152, 491, 196, [86, 90, 51, 22]), (-7.539181, 516, 197, [86, 90, 51, 94]), (-7.661988, 579, 239, [67, 86, 70, 21]), (-7.897076, 464, 152, [90, 51, 94, 26])],
    ((0, 1, 2, 4), 0.6): [(-12.139181, 649, 188, [63, 92, 56, 46]), (-14.745029, 671, 145, [92, 56, 17, 46]), (-18.067836, 734, 115, [63, 77, 9, 75]), (-18.138012, 846, 193, [92, 63, 9, 75])],
}


@pytest.fixture(scope="module")
def index(spark):
    d = Data(spark, "/root/testdata/sf0.01")
    names = {r.key: r.tag for r in d.nations.collect()}
    ix = d.engine().sent().value
    ix.personal = {3: d.engine().index.own(3)}
    assert len(ix.personal[3]) > 10
    return ix, names


def test_known_answers(index):
    ix, names = index
    for (keys, alpha), rows in KNOWN.items():
        got, counters = METHODS["ebs"](ix, QuerySpec(1000, tuple(names[k] for k in keys), alpha, 4))
        assert [(r[1], r[2], r[3], r[4]) for r in got] == rows
        assert counters["orders_evaluated"] <= counters["sets_bp"] * 24
        assert counters["cells_sr"] <= counters["cells_rn"] and counters["sets_sr"] <= counters["sets_rn"]


def test_formulas():
    unit = Arrays(*[None] * 10, {}, 1.0, 10.0)
    assert unit.score(13, 46, 0.5) == 16.5 and unit.score(14, 34, 0.5) == 10
    assert unit.radius(0.5, 85, 10) == pytest.approx(65, abs=1e-4)
    assert unit.radius(0.5, 58, 10) == pytest.approx(38, abs=1e-4)
    assert unit.bound(30, 59, 0.5) == 14.5
    assert unit.radius(0, 85, 10) == float("inf") and unit.radius(0.5, 85, None) == float("inf")
    assert unit.radius(1, 85, -7) == pytest.approx(7, abs=1e-4)


def test_all_variants_equal_brute_force(index):
    ix, names = index
    rnd = random.Random(11)
    variants = [
        {}, {"order": True}, {"budget": 500}, {"dest": 77}, {"ratings": "identical"}, {"route_scope": "all_orders"}, {"prune": frozenset()}, {"prune": frozenset({"cells", "region"})}, {"lower_bound": "zero"},
        {"lower_bound": "grid"}, {"cell_lb": "paper"}, {"tau_scope": "global"}, {"dest": 1500, "order": True, "budget": 900}, {"user": 3}, {"rating_floor": 40},
    ]
    for i in range(75):
        tags = tuple(names[k] for k in rnd.sample(range(25), rnd.choice([1, 2, 3, 4])))
        q = QuerySpec(rnd.randrange(2000), tags, rnd.choice([0, 0.2, 0.6, 0.8, 1]), rnd.choice([1, 2, 4, 6]), **variants[i % len(variants)])
        exact = METHODS["exhaustive"](ix, q)[0]
        assert METHODS["ebs"](ix, q)[0] == exact, q
        if q.order:
            assert METHODS["ordered_pref"](ix, q)[0] == exact
        if len(tags) < 4:
            assert METHODS["progressive"](ix, q)[0] == exact
        if exact:
            for m in ("greedy_nearest", "greedy_rating"):
                for r in METHODS[m](ix, q)[0]:
                    assert r[1] <= exact[0][1] + 1e-6


def test_many_tags(index, monkeypatch):
    """Best orders from subsets equal those from lists; nine tags, and orders of precedence."""
    ix, names = index
    rnd = random.Random(5)
    for _ in range(12):
        tags = tuple(names[k] for k in rnd.sample(range(25), 4))
        q = QuerySpec(rnd.randrange(2000), tags, 0.6, 3, dest=rnd.choice([None, 77]), budget=rnd.choice([None, 700]), precedence=rnd.choice([(), ((tags[0], tags[2]), (tags[2], tags[1]))]))
        listed = METHODS["ebs"](ix, q)[0]
        with monkeypatch.context() as m:
            m.setattr(search, "MOST_LISTED", 1)
            assert METHODS["ebs"](ix, q)[0] == listed
    few = {t: found[:2] for t, found in ix.by_tag.items()}
    small = replace(ix, by_tag=few)
    q = QuerySpec(1000, tuple(names[k] for k in range(9)), 0.6, 3)
    best = METHODS["ebs"](small, q)[0]
    legs, ranked = search.Legs(small, q), []
    for members in itertools.product(*(few[t].tolist() for t in q.tags)):
        d, pois = legs.best_order(list(members), float("inf"))
        rating = sum(int(small.poi_rating[p]) for p in members)
        ranked.append((-small.score(d, rating, 0.6), d, pois, rating))
    assert [(-s, d, list(p)) for s, d, p, _ in sorted(ranked)[:3]] == [(r[1], r[2], r[4]) for r in best]
    order = list(itertools.islice(itertools.permutations(range(9)), 0, 362880, 997))
    members = [int(few[t][0]) for t in q.tags]
    assert legs.best_order(members, float("inf"))[0] <= min(legs.route([members[j] for j in o]) for o in order)


def test_spot_rows_keep_what_was_asked(index):
    ix, _ = index
    rows = SpotRows(ix.net, ix.poi_v)
    for limit in (40, 200, 10**6, int(FAR)):
        for a, b in itertools.islice(itertools.product(rows.spots.tolist(), repeat=2), 0, None, 97):
            exact, got = int(ix.net.distances(a)[b]), rows.between(a, b, limit, rows.spots[:9].tolist())
            assert got == exact if exact <= limit else got > limit
    dist = ix.overlay.reach(np.array([5, 9]), np.array([0, 30]), 500)
    exact = np.minimum(ix.net.distances(int(ix.overlay.ids[5])), ix.net.distances(int(ix.overlay.ids[9])) + 30)[ix.overlay.ids]
    assert (dist == np.where(exact <= 500, exact, FAR)).all()


def test_edges_of_the_definition(index):
    ix, names = index
    assert METHODS["ebs"](ix, QuerySpec(0, ("no such tag",)))[0] == []
    assert METHODS["ebs"](ix, QuerySpec(10**9, (names[3],)))[0] == []
    assert QuerySpec(0, ("a", "a", "b")).tags == ("a", "b")
    every = METHODS["ebs"](ix, QuerySpec(0, (names[3], names[5]), 0.6, 10**6))[0]
    few = METHODS["ebs"](ix, QuerySpec(0, (names[3], names[5]), 0.6, 3))[0]
    assert every[:3] == few and len(every) == len(ix.by_tag[names[3]]) * len(ix.by_tag[names[5]])
    at_poi = int(ix.net.ids[ix.poi_v[ix.by_tag[names[3]][0]]])
    assert METHODS["ebs"](ix, QuerySpec(at_poi, (names[3],), 1.0, 1))[0][0][2] == 0
    assert METHODS["ebs"](ix, QuerySpec(0, (names[3],), budget=0))[0] == []
    with pytest.raises(ValueError):
        QuerySpec(0, ("a",), alpha=1.5)


def test_tops_fall_with_alpha(index):
    ix, names = index
    tags = tuple(names[k] for k in (3, 5, 7))
    best = [METHODS["ebs"](ix, QuerySpec(1000, tags, a, 1))[0][0] for a in (0.1, 0.3, 0.5, 0.7, 0.9)]
    assert [b[2] for b in best] == sorted((b[2] for b in best), reverse=True)
    assert [b[3] for b in best] == sorted((b[3] for b in best), reverse=True)


def test_exhaustive_by_completions(index, monkeypatch):
    """Routes judged together give what listing them one by one gives, whatever the variant."""
    ix, names = index
    rnd = random.Random(3)
    variants = [{}, {"order": True}, {"budget": 500}, {"dest": 77}, {"ratings": "identical"}, {"route_scope": "all_orders"}, {"dest": 1500, "order": True, "budget": 900}, {"user": 3}]
    for i in range(48):
        tags = tuple(names[k] for k in rnd.sample(range(25), rnd.choice([1, 3, 4])))
        q = QuerySpec(rnd.randrange(2000), tags, rnd.choice([0, 0.2, 0.6, 1]), rnd.choice([1, 4, 6]), **variants[i % len(variants)])
        listed = METHODS["exhaustive"](ix, q)[0]
        with monkeypatch.context() as m:
            m.setattr(local, "MOST_ROUTES", 0)
            assert METHODS["exhaustive"](ix, q)[0] == listed, q


def test_exhaustive_of_many_places(index):
    """Forty places a tag, 61 million routes: not one by one."""
    ix, names = index
    many = replace(ix, by_tag={names[k]: np.arange(len(ix.poi))[k % 2 :: 2][:40] for k in range(4)})
    q = QuerySpec(1000, tuple(names[k] for k in range(4)), 0.6, 4)
    rows, counters = METHODS["exhaustive"](many, q)
    assert len(rows) == 4 and counters["routes"] < 10**6
    assert [r[1:4] for r in rows] == [r[1:4] for r in METHODS["ebs"](many, q)[0]]
