from pyspark.sql import functions as F

from tagroute import index, network, operators, partition
from tagroute.distance import same_cell_true, sssp
from tagroute.query import Engine, QuerySpec, RouteIndex
from tagroute.registry import Data
from tagroute.sources.edge_list import edges_from_text, register_edge_list


def test_partitions_keep_their_bound(spark, sf_dir):
    d = Data(spark, sf_dir)
    for cells in (partition.kd(d.vertices, 32), partition.multilevel(d.edges, 32), partition.propagate(d.edges, 32)):
        assert cells.count() == 200 and cells.select("v").distinct().count() == 200
        assert cells.groupBy("cell").count().agg(F.max("count")).first()[0] <= 32


def test_same_cell_distances_by_rounds(spark, sf_dir):
    d = Data(spark, sf_dir)
    closed = index.materialize(index.closure(d.edges, d.cells), "closed")
    true = same_cell_true(closed, d.cross, d.cells, d.border)
    direct = sssp(d.arcs, d.vertices.select(F.col("v").alias("s")))
    wrong = true.join(direct.select(F.col("s").alias("u"), "v", F.col("dist").alias("d")), ["u", "v"]).filter("dist <> d")
    assert true.count() >= closed.count() and wrong.count() == 0  # a pair may have no way inside its cell


def test_index_round_trip_and_partitioners_agree(spark, sf_dir, tmp_path):
    d = Data(spark, sf_dir)
    pois = network.pois_part(spark, sf_dir)
    tags = [r[0] for r in pois.select("tag").distinct().orderBy("tag").limit(3).collect()]
    one = Engine.build(d.vertices, d.edges, pois, partition.kd(d.vertices, 24))
    two = Engine.build(d.vertices, d.edges, pois, partition.tiles(d.vertices, 40))
    one.index.save(str(tmp_path))
    three = Engine(RouteIndex.load(spark, str(tmp_path)))
    a, b, c = (e.routes(5, tags, 4, 0.5).orderBy("rank").collect() for e in (one, two, three))
    assert a == b == c and len(a) == 4
    assert one.explain(QuerySpec(5, tuple(tags))).count() >= 1
    two.register_sql()
    got = spark.sql(f"SELECT * FROM tcr_routes(5L, array({', '.join(repr(t) for t in tags)}), 4, 0.5D)").count()
    assert got == 4


def test_edge_lists(spark, tmp_path):
    p = tmp_path / "net.txt"
    p.write_text("# id u v w\n0 1 2 10\n1 3 2 7.0\n\n2 3 4 1\n")
    register_edge_list(spark)
    rows = sorted(tuple(r) for r in spark.read.format("edge_list").option("rangeBytes", 9).load(str(p)).collect())
    assert rows == [(1, 2, 10), (2, 3, 7), (3, 4, 1)] == sorted(tuple(r) for r in edges_from_text(spark, str(p)).collect())


def test_components_of_a_cut_network(spark):
    edges = spark.createDataFrame([(0, 1), (1, 2), (5, 6), (8, 7), (7, 5)], "u long, v long")
    got = {r.v: r.root for r in operators.connected(edges).collect()}
    assert got == {0: 0, 1: 0, 2: 0, 5: 5, 6: 5, 7: 5, 8: 5}


def test_components_of_a_long_way_settle_in_few_rounds(spark):
    """A path of 3,000 vertices in no order, a loop alone, and parallel edges."""
    at = [v * 1237 % 3001 for v in range(3001)]
    edges = [*zip(at, at[1:]), (5000, 5000), (5001, 5002), (5002, 5001)]
    got = {r.v: r.root for r in operators.connected(spark.createDataFrame(edges, "u long, v long"), max_rounds=14).collect()}
    assert got == {v: 0 for v in at} | {5000: 5000, 5001: 5001, 5002: 5001}


def test_scope_follows_the_tables(spark, sf_dir):
    """Another number of suppliers and vertices, another share."""
    from tagroute.registry import QUERIES

    small, larger = (sorted(map(tuple, QUERIES["m_scope"](spark, d).collect())) for d in (sf_dir, "/root/testdata/sf0.01"))
    assert [r[0] for r in small] == [r[0] for r in larger] == [3, 4, 5] and all(a[1] > b[1] for a, b in zip(small, larger))


def test_distances_over_strips(spark, sf_dir, monkeypatch):
    """A network beyond a task, by strips: landmarks, a limit, a source that no arc has, and a graph of shortcuts."""
    from tagroute.distance import arrays
    from tagroute.distance.wide import sssp_strips

    d = Data(spark, sf_dir)
    asked = index.spread_landmarks(d.vertices, 4).select(F.col("v").alias("s")).unionByName(spark.createDataFrame([(10**6,)], "s long"))
    for limit in (None, 60):
        expected = sorted(map(tuple, sssp(d.arcs, asked, limit).collect()))
        assert sorted(map(tuple, sssp_strips(d.arcs, asked, limit, most=150).collect())) == expected
    monkeypatch.setattr(arrays, "LOCAL_ARCS", 100)
    assert index.landmarks(d.arcs, index.spread_landmarks(d.vertices, 8)).count() == 8 * 200
