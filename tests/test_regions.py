"""Networks beyond a task by parts: the same answers and counters as over the whole network."""

import pytest
from pyspark.sql import functions as F

from tagroute import network
from tagroute.query import Engine, regions
from tagroute.registry import Data

BIG = "/root/testdata/sf0.01"
DEST = {"dest": 300}


@pytest.fixture(scope="module")
def engines(spark):
    """Every third vertex has one of two tags, and the network is beyond a task from 100 arcs on."""
    d = Data(spark, BIG)
    pois = d.vertices.filter("v % 3 = 0").select(F.col("v").alias("poi"), "v", F.when(F.col("v") * 7 % 5 < 3, "even").otherwise("odd").alias("tag"), (1 + F.col("v") * 37 % 90).alias("rating"))
    local = Engine.build(d.vertices, d.edges, pois.unionByName(d.pois), d.cells, personal=network.personal_ratings(spark, BIG))
    wide = Engine(local.index, limit=100)
    assert local.mode() == "local" and wide.mode() == "wide"
    return local, wide


@pytest.fixture(scope="module")
def asked(spark):
    rows = [(q, 137 * q % 2000, ["even", "odd"] if q % 2 else ["odd", "even"], 0.8, 3, None, None) for q in range(12)] + [(50, 10**9, ["even"], 0.8, 3, None, None), (51, 3, ["none"], 0.8, 3, None, None)]
    return spark.createDataFrame(rows, "qid long, v_q long, tags array<string>, alpha double, k int, dest long, budget long")


def _check(engines, asked, monkeypatch, method, parts=True, **variant):
    """Equal answers, from parts that are smaller than the network."""
    monkeypatch.setattr(regions, "BLOCK", 16)
    monkeypatch.setattr(regions, "SQUARE", 1)
    local, wide = engines
    expected = sorted(map(tuple, local.run(asked, method, **variant).collect()))
    limit = 6000 if parts else 10**6
    got = sorted(map(tuple, regions.run_regions(wide.index, asked, method, variant, limit=limit).collect()))
    assert got == expected and len({r[0] for r in expected}) >= 5


def test_parts_that_do_not_fit_are_refused(engines, asked):
    with pytest.raises(ValueError):
        regions.run_regions(engines[1].index, asked, "progressive", {"order": True}, limit=100)


def test_budget_that_ends_before_the_destination(engines, asked, monkeypatch):
    """No answer is an answer: the destination lies outside the part that the budget allows."""
    assert regions.run_regions(engines[1].index, asked, "budget_labels", {"budget": 20, "dest": 1990}).count() == engines[0].run(asked, "budget_labels", budget=20, dest=1990).count()


def test_budget_labels_fixed(engines, asked, monkeypatch):
    _check(engines, asked, monkeypatch, "budget_labels", budget=60, order=True)


def test_budget_labels(engines, asked, monkeypatch):
    _check(engines, asked, monkeypatch, "budget_labels", budget=60)


def test_dominance(engines, asked, monkeypatch):
    _check(engines, asked, monkeypatch, "dominance", ratings="identical", route_scope="all_orders")


def test_dominance_fixed(engines, asked, monkeypatch):
    _check(engines, asked, monkeypatch, "dominance", ratings="identical", order=True)


def test_greedy_nearest(engines, asked, monkeypatch):
    _check(engines, asked, monkeypatch, "greedy_nearest")


def test_greedy_rating(engines, asked, monkeypatch):
    _check(engines, asked, monkeypatch, "greedy_rating", parts=False)


def test_best_rated_places_may_lie_anywhere(engines, asked):
    """No part of the network as large as the whole one goes to a task, however far the hops are."""
    local, wide = engines
    for variant in ({"order": True, **DEST}, {"ratings": "identical", "budget": 60}):
        expected = sorted(map(tuple, local.run(asked, "greedy_rating", **variant).collect()))
        assert sorted(map(tuple, regions.run_regions(wide.index, asked, "greedy_rating", variant, limit=100).collect())) == expected
        assert len(expected) >= 5


def test_ordered_pref(engines, asked, monkeypatch):
    _check(engines, asked, monkeypatch, "ordered_pref", parts=False, order=True, **DEST)


def test_ordered_pref_nodest(engines, asked, monkeypatch):
    _check(engines, asked, monkeypatch, "ordered_pref", order=True)


def test_progressive(engines, asked, monkeypatch):
    _check(engines, asked, monkeypatch, "progressive", order=True)


def test_ordered_astar(engines, asked, monkeypatch):
    _check(engines, asked, monkeypatch, "ordered_astar", ratings="identical", order=True)


def test_ebs(engines, asked, monkeypatch):
    _check(engines, asked, monkeypatch, "ebs")
    _check(engines, asked, monkeypatch, "ebs", parts=False, rating_scope="path")


def test_counters(engines, asked, monkeypatch):
    """Every counter of the search is that over the whole network."""
    monkeypatch.setattr(regions, "BLOCK", 16)
    local, wide = engines
    told = lambda e: {r.qid: r.counters for r in e.counters(asked).collect()}
    assert told(wide) == told(local)


def test_counters_from_narrow_parts(engines, asked, monkeypatch):
    """Parts that reach as far as routes that count may go are enough: twice what the search settled is not asked for."""
    monkeypatch.setattr(regions, "BLOCK", 16)
    monkeypatch.setattr(regions, "SQUARE", 1)
    local, wide = engines
    got = regions.run_regions(wide.index, asked, "ebs", {}, counters=True, limit=5500)
    assert {r.qid: r.counters for r in got.collect()} == {r.qid: r.counters for r in local.counters(asked).collect()}


@pytest.mark.parametrize(("method", "variant"), [("ordered_pref", {}), ("ordered_astar", {"ratings": "identical"})])
def test_ways_to_a_destination_widen_by_their_length(engines, asked, monkeypatch, method, variant):
    """Where the first part has no answer, the next has room beside the way to the destination, and is not the whole network."""
    monkeypatch.setattr(regions, "BLOCK", 16)
    monkeypatch.setattr(regions, "SQUARE", 1)
    local, wide = engines
    got = regions.run_regions(wide.index, asked, method, {"order": True, **DEST, **variant}, limit=7200)
    assert sorted(map(tuple, got.collect())) == sorted(map(tuple, local.run(asked, method, order=True, **DEST, **variant).collect()))


def test_many_starts_in_a_square_are_dealt_out(spark):
    """Queries that start together go to several tasks, about as many to each."""
    waiting = spark.range(320).select(F.col("id").alias("qid"), F.lit(5.0).alias("sx"), (F.col("id") % 7).cast("double").alias("sy"))
    sizes = [r["count"] for r in regions._squares(waiting, 100).groupBy("g").count().collect()]
    assert sum(sizes) == 320 and len(sizes) == 20 and max(sizes) <= 40
