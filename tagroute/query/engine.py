from __future__ import annotations

import json
from collections.abc import Iterator
from dataclasses import dataclass

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from .. import index as ix_frames
from .. import network, partition
from ..distance.arrays import Csr, collect_csr
from ..functions import RATIO
from ..plans.mode import LOCAL_ARCS, choose_mode
from ..plans.rounds import materialize
from .search import Arrays
from .regions import run_regions
from .spec import QuerySpec, queries_frame
from .wide import VARIANTS, run_wide

ANSWER_SCHEMA = "qid long, rank int, score double, dist long, rating long, pois array<long>"
#: Shortcuts that may be sent for each arc that may.
SHORTCUTS_AN_ARC = 8
COUNTER_SCHEMA = "qid long, counters map<string,long>, seconds double"


@dataclass
class RouteIndex:
    """An index as DataFrames, which can be saved and loaded, and as arrays for tasks."""

    vertices: DataFrame
    edges: DataFrame
    cells: DataFrame
    pois: DataFrame
    border: DataFrame
    cross: DataFrame
    shortcuts: DataFrame  # (u, v, dist)
    w_max: float = 19
    r_max: float = 90
    ratio: float = 10
    personal: DataFrame | None = None

    _TABLES = ("vertices", "edges", "cells", "pois", "border", "cross", "shortcuts")

    def save(self, path: str) -> None:
        for t in self._TABLES:
            getattr(self, t).write.mode("overwrite").parquet(f"{path}/{t}")
        spark = self.edges.sparkSession
        spark.createDataFrame([(float(self.w_max), float(self.r_max), float(self.ratio))], "w_max double, r_max double, ratio double").write.mode("overwrite").parquet(f"{path}/scale")

    @classmethod
    def load(cls, spark: SparkSession, path: str) -> RouteIndex:
        s = spark.read.parquet(f"{path}/scale").first()
        return cls(*(spark.read.parquet(f"{path}/{t}") for t in cls._TABLES), s.w_max, s.r_max, s.ratio)

    def own(self, user: int) -> dict[int, int]:
        """A user's own ratings by POI: one number a POI of the layer at most."""
        if self.personal is None:
            return {}
        found = self.personal.filter(F.col("user") == user).groupBy("poi").agg(F.max("rating").alias("rating")).join(self.pois.select("poi").distinct(), "poi", "left_semi").toArrow()
        return dict(zip(found.column("poi").to_pylist(), found.column("rating").to_pylist(), strict=True))

    def fits(self, limit: int) -> bool:
        """Whether arcs, POIs, borders and shortcuts are few enough to be sent to tasks; counted up to the limits alone."""
        most = ((network.arcs(self.edges), limit), (self.pois, limit), (self.border, limit), (self.shortcuts, SHORTCUTS_AN_ARC * limit))
        return all(choose_mode(df, n) == "local" for df, n in most)

    def arrays(self, limit: int = LOCAL_ARCS) -> Arrays:
        """On the driver, for networks of a checked size; the caller broadcasts it."""
        if not self.fits(limit):
            raise ValueError(f"more than {limit} arcs or POIs: use the wide mode")
        net = collect_csr(network.arcs(self.edges), self.vertices, limit)
        v = self.vertices.join(self.cells, "v").select("v", "x", "y", "cell").toArrow()
        order = np.searchsorted(net.ids, v.column("v").to_numpy())
        x, y, cell = (np.zeros(len(net.ids), t) for t in (np.int64, np.int64, np.int64))
        x[order], y[order], cell[order] = (v.column(c).to_numpy() for c in ("x", "y", "cell"))
        border = np.zeros(len(net.ids), bool)
        border[np.searchsorted(net.ids, self.border.select("v").toArrow().column("v").to_numpy())] = True
        shortcuts: dict[int, list[tuple[int, int]]] = {}
        s = self.shortcuts.select("u", "v", "dist").toArrow()
        su, sv, sd = np.searchsorted(net.ids, s.column("u").to_numpy()), np.searchsorted(net.ids, s.column("v").to_numpy()), s.column("dist").to_numpy()
        for a, b, d in zip(su.tolist(), sv.tolist(), sd.tolist(), strict=True):
            shortcuts.setdefault(a, []).append((b, d))
        tail = np.repeat(np.arange(len(net.ids)), np.diff(net.ptr))
        cross = cell[tail] != cell[net.head]
        overlay = Csr(np.concatenate((su, tail[cross])), np.concatenate((sv, net.head[cross])), np.concatenate((sd, net.w[cross])), np.flatnonzero(border))
        p = self.pois.select("poi", "v", "tag", "rating").orderBy("poi", "tag").toArrow()
        at = np.searchsorted(net.ids, p.column("v").to_numpy())
        ok = (at < len(net.ids)) & (net.ids[np.minimum(at, len(net.ids) - 1)] == p.column("v").to_numpy())
        p, at = p.filter(pa.array(ok)), at[ok]
        tags = np.array(p.column("tag").to_pylist(), object)
        by_tag = {t: np.flatnonzero(tags == t) for t in set(tags.tolist())}
        return Arrays(net, x, y, cell, border, shortcuts, p.column("poi").to_numpy(), at, p.column("rating").to_numpy(), by_tag, {}, self.w_max, self.r_max, self.ratio, overlay)


class Engine:
    """Builds indexes and runs queries over them.

    Batches are spread over tasks by query; each task has the index as arrays, so the network's
    size is checked first (`limit` arcs).  Batches over larger networks go through `query.wide`, which
    has no baselines, path ratings or choice of bounds and raises ValueError for these; `run` and `counters` go
    through `query.regions` there, which has all of them.
    """

    def __init__(self, index: RouteIndex, limit: int = LOCAL_ARCS):
        self.index, self.spark = index, index.edges.sparkSession
        self._sent, self.limit, self._told = None, limit, {}
        self._mode, self._closed = None, None

    @classmethod
    def build(cls, vertices: DataFrame, edges: DataFrame, pois: DataFrame, cells: DataFrame | None = None, side: int = 70, w_max: float = 19, r_max: float = 90, personal: DataFrame | None = None, limit: int = LOCAL_ARCS) -> Engine:
        cells = partition.tiles(vertices, side) if cells is None else cells
        cross = ix_frames.cross_edges(edges, cells)
        border = ix_frames.borders(cross)
        closed = ix_frames.closure(edges, cells, level="border")
        short = closed.join(border, ["cell", "v"], "left_semi").filter("u <> v").select("u", "v", "dist")
        return cls(RouteIndex(vertices, edges, cells, pois, border, cross, short, w_max, r_max, personal=personal), limit)

    def sent(self):
        if self._sent is None:
            self._sent = self.spark.sparkContext.broadcast(self.index.arrays(self.limit))
        return self._sent

    def mode(self) -> str:
        if self._mode is None:
            self._mode = "local" if self._sent is not None else ("local" if self.index.fits(self.limit) else "wide")
        return self._mode

    def _run_wide(self, queries: DataFrame, method: str, variant: dict) -> DataFrame:
        if method != "ebs":
            raise ValueError(f"{method} is not in the wide mode")
        ix, usual = self.index, QuerySpec(0, ("",))
        given = {n: v for n, v in variant.items() if n in ("v_q", "alpha", "k", "dest", "budget")}
        rest = {n: v for n, v in variant.items() if n not in given and (n in VARIANTS or v != getattr(usual, n))}
        asked = queries.withColumns({n: F.lit(v).cast(queries.schema[n].dataType) for n, v in given.items()}) if given else queries
        asked = asked.select("qid", "v_q", "tags", "alpha", "k", "dest", "budget").filter("v_q is not null and size(tags) > 0")
        if self._closed is None:
            self._closed = materialize(ix_frames.closure(ix.edges, ix.cells), "closed")
        return run_wide(ix_frames.tag_index(ix.pois, ix.cells), ix.cells, self._closed, ix.cross, asked, personal=ix.personal, w_max=ix.w_max, r_max=ix.r_max * RATIO / ix.ratio, **rest)

    def _run(self, queries: DataFrame, method: str, variant: dict, schema: str) -> DataFrame:
        sent = self.sent()
        counters_only = schema == COUNTER_SCHEMA
        user = variant.get("user")
        own = self.spark.sparkContext.broadcast({user: self.index.own(user)} if user is not None else {})

        def each(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
            import time

            from ..baselines.local import METHODS

            index, search = sent.value, METHODS[method]
            index.personal = own.value
            for b in batches:
                rows = []
                for q in b.to_pylist():
                    given = {"qid": q["qid"], "v_q": q["v_q"], "tags": tuple(q["tags"]), "alpha": q["alpha"], "k": q["k"], "dest": q["dest"], "budget": q["budget"]} | variant
                    began = time.perf_counter()
                    answers, counters = search(index, QuerySpec(**given))
                    if counters_only:
                        rows.append((q["qid"], counters, time.perf_counter() - began))
                    else:
                        rows += [(q["qid"], *a) for a in answers]
                if not rows:
                    continue
                c = list(zip(*rows, strict=True))
                if counters_only:
                    yield pa.record_batch([pa.array(c[0], pa.int64()), pa.array([list(x.items()) for x in c[1]], pa.map_(pa.string(), pa.int64())), pa.array(c[2], pa.float64())], ["qid", "counters", "seconds"])
                else:
                    yield pa.record_batch([pa.array(c[0], pa.int64()), pa.array(c[1], pa.int32()), pa.array(c[2], pa.float64()), pa.array(c[3], pa.int64()), pa.array(c[4], pa.int64()), pa.array(c[5], pa.list_(pa.int64()))], ["qid", "rank", "score", "dist", "rating", "pois"])

        asked = queries.select("qid", "v_q", "tags", "alpha", "k", "dest", "budget").filter("v_q is not null and size(tags) > 0")
        # queries that start together go to one task, which has their distances once; rows are few and dear, so the number
        # of tasks is ours and not left to their bytes
        parts = int(self.spark.conf.get("spark.sql.shuffle.partitions"))
        return asked.repartition(max(parts, 2 * self.spark.sparkContext.defaultParallelism), F.col("v_q")).sortWithinPartitions("v_q").mapInArrow(each, schema)

    def run_batch(self, queries: DataFrame, method: str = "ebs", **variant) -> DataFrame:
        """Answers of a batch: (qid, rank, score, dist, rating, pois in order of visit)."""
        return self._run_wide(queries, method, variant) if self.mode() == "wide" else self._run(queries, method, variant, ANSWER_SCHEMA)

    def run(self, queries: DataFrame, method: str = "ebs", **variant) -> DataFrame:
        """As `run_batch`, and over larger networks by any method: each query gets the part of the network that its answers can lie in."""
        if self.mode() == "local":
            return self._run(queries, method, variant, ANSWER_SCHEMA)
        return run_regions(self.index, queries, method, variant)

    def counters(self, queries: DataFrame, method: str = "ebs", **variant) -> DataFrame:
        """What each query's search counted, and its seconds; run once for the same queries, method and variant."""
        key = (queries.semanticHash(), method, repr(sorted(variant.items(), key=str)))
        if key not in self._told:
            counted = self._run(queries, method, variant, COUNTER_SCHEMA) if self.mode() == "local" else run_regions(self.index, queries, method, variant, counters=True)
            self._told[key] = materialize(counted, "counters")
        return self._told[key]

    def routes(self, v_q: int, tags: list[str], k: int = 4, alpha: float = 0.6, method: str = "ebs", **variant) -> DataFrame:
        spec = QuerySpec(v_q, tuple(tags), alpha, k, **{n: v for n, v in variant.items() if n in ("dest", "budget")})
        rest = {n: v for n, v in variant.items() if n not in ("dest", "budget")}
        return self.run_batch(queries_frame(self.spark, [spec]), method, **rest)

    def unfold(self, answers: DataFrame, queries: DataFrame) -> DataFrame:
        """(qid, rank, path): every vertex of each route."""
        sent = self.sent()

        def each(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
            ix = sent.value
            place = {int(p): int(v) for p, v in zip(ix.poi, ix.poi_v, strict=True)}
            for b in batches:
                paths = []
                for v_q, pois, dest in zip(*(b.column(c).to_pylist() for c in ("v_q", "pois", "dest")), strict=True):
                    at = ix.net.rank(v_q)
                    out = [at]
                    for v in [*(place[p] for p in pois), *([ix.net.rank(dest)] if dest is not None else [])]:
                        out += ix.net.path(at, v)[1:]
                        at = v
                    paths.append(ix.net.ids[out].tolist())
                yield pa.record_batch([b.column("qid"), b.column("rank"), pa.array(paths, pa.list_(pa.int64()))], ["qid", "rank", "path"])

        return answers.join(queries.select("qid", "v_q", "dest"), "qid").select("qid", "rank", "pois", "v_q", "dest").mapInArrow(each, "qid long, rank int, path array<long>")

    def explain(self, spec: QuerySpec) -> DataFrame:
        """One row a stage of a query's region: radius, cells inside, and maxima's sum; then the counters."""
        from .search import explore_and_bound

        trace: list = []
        _, counters = explore_and_bound(self.sent().value, spec, trace)
        rows = [(f"region {i}", float(r) if r != float("inf") else None, int(c), float(t), None) for i, (r, c, t) in enumerate(trace)]
        return self.spark.createDataFrame([*rows, ("counters", None, None, None, json.dumps(counters))], "stage string, radius double, cells int, tau double, counters string")

    def register_sql(self, name: str = "tcr_routes") -> None:
        """A SQL table function: tcr_routes(v_q, array of tags, k, alpha)."""
        from pyspark.sql.functions import udtf

        sent = self.sent()

        @udtf(returnType="rank int, score double, dist bigint, rating bigint, pois array<bigint>")
        class Routes:
            def eval(self, v_q: int, tags: list, k: int, alpha: float):
                from tagroute.query.search import explore_and_bound

                yield from explore_and_bound(sent.value, QuerySpec(v_q, tuple(tags), float(alpha), int(k)))[0]

        self.spark.udtf.register(name, Routes)


