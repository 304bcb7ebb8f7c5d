"""Whole results where a shortcut would lose some."""

import os

import duckdb
import pytest
from pyspark.sql import functions as F

from tagroute import network, workloads
from tagroute.query import Engine, QuerySpec, queries_frame, regions
from tagroute.registry import ORACLE_SQL, QUERIES, Data
from tagroute.sources.tables import TABLES


def test_snap_finds_far_vertices(spark):
    vertices = [(v, 10 * (v % 5), 10 * (v // 5)) for v in range(23)]
    points = [(1, 3, 4), (2, 45, 70), (3, 900, -400), (4, 61, 0), (5, 20, 60), (6, None, 5)]
    got = network.snap_nearest(spark.createDataFrame(points, "id long, px long, py long"), spark.createDataFrame(vertices, "v long, x long, y long"))
    nearest = {i: min(vertices, key=lambda r: ((r[1] - px) ** 2 + (r[2] - py) ** 2, r[0]))[0] for i, px, py in points if px is not None}
    assert {r.id: r.v for r in got.collect()} == nearest and got.count() == 5


def test_networks_beyond_a_task_have_the_same_answers(spark, sf_dir):
    """Mixed numbers of tags, destinations, orders and ratings, and POIs of two tags, in the wide mode that the engine chooses."""
    d = Data(spark, sf_dir)
    pois = d.pois.unionByName(d.pois.filter("poi % 2 = 0").withColumn("tag", F.lit("even"))).unionByName(d.pois.filter("poi % 4 = 0").withColumn("tag", F.lit("fourth")))
    local = Engine.build(d.vertices, d.edges, pois, d.cells, personal=d.pois.select(F.lit(3).cast("long").alias("user"), "poi", (91 - F.col("rating")).alias("rating")))
    wide = Engine(local.index, limit=100)
    names = [r[0] for r in d.pois.select("tag").distinct().orderBy("tag").limit(2).collect()]
    specs = [QuerySpec(100, ("even", "fourth"), 0.6, 4, 0), QuerySpec(7, ("fourth", names[0], "even"), 0.4, 3, 1, dest=150), QuerySpec(30, (names[1],), 0.2, 2, 2), QuerySpec(60, ("even", names[1]), 0.0, 5, 3, dest=3, budget=400)]
    identical, personal = {"order": True, "ratings": "identical"}, {"precedence": (("even", "fourth"),), "user": 3, "rating_floor": 20, "route_scope": "all_orders"}
    for some, variant in ((specs, {}), (specs[1:2], identical), (specs[:1], personal)):
        asked = queries_frame(spark, some)
        expected = sorted(map(tuple, local.run_batch(asked, **variant).collect()))
        assert {r[0] for r in expected} == {s.qid for s in some}
        assert sorted(map(tuple, wide.run_batch(asked, **variant).collect())) == expected, variant
    for refused in ({"rating_scope": "path"}, {"epsilon": 0.1}, {"method": "progressive"}):
        with pytest.raises(ValueError):
            wide.run_batch(asked, **refused)


def test_workloads_run_their_grids(spark, sf_dir, monkeypatch):
    """Every point with every method; the label search within its budget finds the best route that the others find."""
    d = Data(spark, sf_dir)
    few = lambda m, k, a, dest=False: d.log(m, k, a).filter("qid < 4")
    engine, points = d.engine("documents"), len(workloads.GRID["m"])
    tags = d.engine("documents").index.pois.select("tag").distinct().orderBy("tag").limit(5)
    named = F.array(*(F.lit(r[0]) for r in tags.collect()))
    log = lambda m, k, a, dest=False: few(m, k, a).withColumn("tags", F.slice(named, 1, m))
    got = workloads.comparison(engine, log, "fixed_varying_nodest").collect()
    assert len(got) == points * 3 and {r.m for r in got} == set(workloads.GRID["m"])
    score = {(r.m, r.method): r.score for r in got}
    for m in workloads.GRID["m"]:
        assert score[m, "budget_labels"] == score[m, "ebs"] is not None
    monkeypatch.setattr(workloads, "GRID", {"k": (2, 4)})
    found = workloads.effectiveness(engine, log).collect()
    assert len(found) == 3 * len(workloads.EFFECTIVENESS)
    work = workloads.ablation(engine, log).collect()
    assert len(work) == (2 + len(workloads.SHARES)) * len(workloads.ABLATIONS) and {r.share for r in work} == {0.25, 0.5, 0.75, 1.0}


def test_pruning_cube_has_the_queries_of_all_events(spark, sf_dir, tmp_path):
    """Events numbered 990 to 1009: half of them lie beyond the experiments' workload."""
    con = duckdb.connect()
    for t in TABLES:
        if t == "events":
            con.execute(f"COPY (SELECT * REPLACE (event_id + 990 AS event_id) FROM '{sf_dir}/events.parquet' WHERE event_id < 20) TO '{tmp_path}/events.parquet'")
        else:
            os.symlink(f"{sf_dir}/{t}.parquet", tmp_path / f"{t}.parquet")
        con.execute(f"CREATE VIEW {t} AS SELECT * FROM read_parquet('{tmp_path}/{t}.parquet')")
    asked = Data(spark, str(tmp_path)).log(whole=True)
    assert asked.filter("qid >= 1000").count() == 10
    got = sorted(map(repr, map(tuple, QUERIES["cube_pruning"](spark, str(tmp_path)).select("zone", "parity", "queries", "cells_rn", "shrinks").collect())))
    assert got == sorted(map(repr, con.execute(ORACLE_SQL["cube_pruning"]).fetchall()))
    assert con.execute("SELECT queries FROM (" + ORACLE_SQL["cube_pruning"] + ") AS c WHERE zone IS NULL AND parity IS NULL").fetchone()[0] > 10


def test_groups_of_large_batches_are_few(spark, monkeypatch):
    """Blocks are sent to each group, so groups don't grow with the batch."""
    monkeypatch.setattr(regions, "GROUPS", 4)
    waiting = spark.range(320).select(F.col("id").alias("qid"), F.lit(5.0).alias("sx"), F.lit(5.0).alias("sy"))
    assert regions._squares(waiting, 100).select("g").distinct().count() <= 4
