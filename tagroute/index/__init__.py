"""Index of a network: borders, cross edges, cell distances, overlay, tags."""

from __future__ import annotations

import heapq

import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from ..plans.rounds import materialize


def cross_edges(edges: DataFrame, cells: DataFrame) -> DataFrame:
    """(u, v, w, cu, cv): edges whose ends lie in different cells."""
    return edges.join(cells.select(F.col("v").alias("u"), F.col("cell").alias("cu")), "u").join(cells.select("v", F.col("cell").alias("cv")), "v").filter("cu <> cv").select("u", "v", "w", "cu", "cv")


def borders(cross: DataFrame) -> DataFrame:
    """(cell, v): vertices with a neighbour in another cell."""
    return cross.select(F.col("cu").alias("cell"), F.col("u").alias("v")).unionByName(cross.select(F.col("cv").alias("cell"), "v")).distinct()


def inner_arcs(arcs: DataFrame, cells: DataFrame) -> DataFrame:
    """(cell, u, v, w): arcs within a cell."""
    return arcs.join(cells.select(F.col("v").alias("u"), "cell"), "u").join(cells.select("v", F.col("cell").alias("cv")), "v").filter("cell = cv").select("cell", "u", "v", "w")


def dijkstra(adjacent: dict[int, list[tuple[int, int]]], source: int) -> dict[int, int]:
    best, heap, done = {source: 0}, [(0, source)], set()
    while heap:
        d, u = heapq.heappop(heap)
        if u in done:
            continue
        done.add(u)
        for v, w in adjacent.get(u, ()):
            if d + w < best.get(v, 1 << 62):
                best[v] = d + w
                heapq.heappush(heap, (d + w, v))
    return best


def closure(edges: DataFrame, cells: DataFrame, level: str = "full") -> DataFrame:
    """(cell, u, v, dist): least distances inside each cell, from every vertex or (level border) from border vertices.

    Cells are of bounded size, so a cell fits a task whatever the network's size.
    """
    from ..network import arcs

    inside = inner_arcs(arcs(edges), cells).select("cell", "u", "v", "w")
    alone = cells.select("cell", F.col("v").alias("u"), F.col("v"), F.lit(0).cast("long").alias("w"))
    rows = inside.unionByName(alone)
    if level == "border":
        marks = borders(cross_edges(edges, cells)).select("cell", F.col("v").alias("u"), F.lit(None).cast("long").alias("v"), F.lit(0).cast("long").alias("w"))
        rows = rows.unionByName(marks)

    def each(table: pa.Table) -> pa.Table:
        cell = table.column("cell")[0].as_py()
        adjacent: dict[int, list[tuple[int, int]]] = {}
        marked, every = [], set()
        for u, v, w in zip(*(table.column(c).to_pylist() for c in "uvw"), strict=True):
            if v is None:
                marked.append(u)
            else:
                every.add(u)
                if u != v:
                    adjacent.setdefault(u, []).append((v, w))
        us, vs, ds = [], [], []
        for s in sorted(marked if level == "border" else every):
            for v, d in dijkstra(adjacent, s).items():
                us.append(s)
                vs.append(v)
                ds.append(d)
        return pa.table({"cell": pa.array([cell] * len(us), pa.int64()), "u": pa.array(us, pa.int64()), "v": pa.array(vs, pa.int64()), "dist": pa.array(ds, pa.int64())})

    return rows.groupBy("cell").applyInArrow(each, "cell long, u long, v long, dist long")


def overlay(closed: DataFrame, border: DataFrame, cross: DataFrame) -> DataFrame:
    """(u, v, dist, kind): shortcuts between borders of a cell, and cross edges both ways."""
    b = border.select("cell", F.col("v").alias("u"))
    short = closed.join(b, ["cell", "u"], "left_semi").join(border, ["cell", "v"], "left_semi").filter("u <> v").select("u", "v", "dist", F.lit("shortcut").alias("kind"))
    over = cross.select("u", "v", F.col("w").alias("dist"), F.lit("cross").alias("kind"))
    return short.unionByName(over).unionByName(over.select(F.col("v").alias("u"), F.col("u").alias("v"), "dist", "kind"))


def tag_index(pois: DataFrame, cells: DataFrame) -> DataFrame:
    """(tag, poi, v, cell, rating)."""
    return pois.join(cells, "v").select("tag", "poi", "v", "cell", "rating")


def tag_max(index: DataFrame) -> DataFrame:
    return index.groupBy("tag").agg(F.max("rating").alias("rating"), F.count("*").alias("n"))


def tag_cell_max(index: DataFrame) -> DataFrame:
    return index.groupBy("tag", "cell").agg(F.max("rating").alias("rating"), F.count("*").alias("n"))



def spread_landmarks(vertices: DataFrame, n: int = 8) -> DataFrame:
    """(v): n vertices at even steps of a dense numbering."""
    total = vertices.count()
    return vertices.select("v").filter(F.col("v").isin([i * total // n for i in range(n)]))


def landmarks(arcs: DataFrame, chosen: DataFrame) -> DataFrame:
    """(landmark, v, dist) over the whole network."""
    from ..distance.arrays import sssp

    return sssp(arcs, chosen.select(F.col("v").alias("s"))).withColumnRenamed("s", "landmark")


def landmark_bound(pairs: DataFrame, table: DataFrame) -> DataFrame:
    """pairs (..., a, b) -> their columns and bound: the farthest that the distances from any landmark lie apart."""
    a = table.select("landmark", F.col("v").alias("a"), F.col("dist").alias("d1"))
    b = table.select("landmark", F.col("v").alias("b"), F.col("dist").alias("d2"))
    return pairs.join(a, "a").join(b, ["b", "landmark"]).groupBy(*pairs.columns).agg(F.max(F.abs(F.col("d1") - F.col("d2"))).alias("bound"))


__all__ = ["borders", "closure", "cross_edges", "dijkstra", "inner_arcs", "landmark_bound", "landmarks", "materialize", "overlay", "spread_landmarks", "tag_cell_max", "tag_index", "tag_max"]
