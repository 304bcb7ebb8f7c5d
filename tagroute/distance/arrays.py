from __future__ import annotations

import heapq
from collections import OrderedDict
from collections.abc import Callable, Iterator

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame

from ..plans.mode import LOCAL_ARCS, choose_mode

FAR = np.int64(1) << 60
#: Bytes of distances that a task keeps, of whole rows and of rows between spots, and that it works on at once.
KEPT_BYTES, WORK_BYTES = 64 << 20, 32 << 20


class Csr:
    """A network as arrays: vertices by rank, arcs by their tail."""

    def __init__(self, u: np.ndarray, v: np.ndarray, w: np.ndarray, extra: np.ndarray | None = None):
        self.ids = np.unique(np.concatenate((u, v, extra if extra is not None else u[:0])))
        tail, head = np.searchsorted(self.ids, u), np.searchsorted(self.ids, v)
        order = np.lexsort((w, head, tail))
        self.head, self.w = head[order].astype(np.int32), w[order].astype(np.int64)
        self.ptr = np.concatenate(([0], np.cumsum(np.bincount(tail, minlength=len(self.ids)))))
        self._rows = OrderedDict()

    def __getstate__(self) -> dict:
        return self.__dict__ | {"_rows": OrderedDict()}

    def rank(self, vertex: int) -> int | None:
        i = int(np.searchsorted(self.ids, vertex))
        return i if i < len(self.ids) and self.ids[i] == vertex else None

    def _relax(self, dist: np.ndarray, front: np.ndarray, limit: int | None, step: int | None = None) -> None:
        """Rounds over the entries that improved, until none does. dist may hold several rows, one after the other.

        step: a round has the entries within a step of the nearest one, and farther ones wait, as they may still improve.
        """
        n, waiting = len(self.ids), front[:0]
        while len(front):
            if step is not None:
                d = dist[front]
                soon = d <= d.min() + step
                front, waiting = front[soon], front[~soon]
            u = front % n
            count = self.ptr[u + 1] - self.ptr[u]
            at = np.repeat(self.ptr[u] - np.cumsum(count) + count, count) + np.arange(count.sum())
            head, d = self.head[at] + np.repeat(front - u, count), np.repeat(dist[front], count) + self.w[at]
            ok = d < dist[head]
            if limit is not None:
                ok &= d <= limit
            head, d = head[ok], d[ok]
            np.minimum.at(dist, head, d)
            front = np.unique(np.concatenate((waiting, head)))

    def distances(self, source: int, limit: int | None = None) -> np.ndarray:
        """From a vertex (by rank) to all; FAR where there is no way (within the limit). Rows without a limit are kept, as far as KEPT_BYTES go."""
        if limit is None and source in self._rows:
            self._rows.move_to_end(source)
            return self._rows[source]
        dist = np.full(len(self.ids), FAR)
        dist[source] = 0
        self._relax(dist, np.array([source]), limit)
        if limit is None:
            self._rows[source] = dist
            if len(self._rows) > max(2, KEPT_BYTES // max(1, dist.nbytes)):
                self._rows.popitem(last=False)
        return dist

    def reach(self, at: np.ndarray, start: np.ndarray, limit: int | None) -> np.ndarray:
        """From several vertices with distances of their own to all."""
        dist = np.full(len(self.ids), FAR)
        np.minimum.at(dist, at, start)
        if limit is not None:
            dist[dist > limit] = FAR
        self._relax(dist, np.unique(at[dist[at] < FAR]), limit, int(self.w.max()) if len(self.w) else 0)
        return dist

    def many(self, sources: np.ndarray, limit: int | None) -> np.ndarray:
        """Rows of distances from several vertices, side by side."""
        n = len(self.ids)
        dist = np.full(len(sources) * n, FAR)
        front = np.arange(len(sources)) * n + sources
        dist[front] = 0
        self._relax(dist, front, limit)
        return dist.reshape(len(sources), n)

    def pair(self, a: int, b: int, bound: Callable[[int], float] | None = None) -> int:
        """Least distance of two vertices by A*: bound(v) never exceeds the distance from v to b."""
        lb = bound or (lambda v: 0)
        best, heap, done = {a: 0}, [(lb(a), 0, a)], set()
        while heap:
            _, d, u = heapq.heappop(heap)
            if u == b:
                return d
            if u in done:
                continue
            done.add(u)
            for i in range(self.ptr[u], self.ptr[u + 1]):
                v, nd = int(self.head[i]), d + int(self.w[i])
                if nd < best.get(v, FAR):
                    best[v] = nd
                    heapq.heappush(heap, (nd + lb(v), nd, v))
        return int(FAR)

    def path(self, a: int, b: int) -> list[int]:
        """Vertices (by rank) of a shortest path; of several, the one over the least vertices seen from b."""
        dist, out = self.distances(a), [b]
        while out[-1] != a:
            u = out[-1]
            out.append(min(int(self.head[i]) for i in range(self.ptr[u], self.ptr[u + 1]) if dist[self.head[i]] + self.w[i] == dist[u]))
        return out[::-1]


class SpotRows:
    """Distances between marked vertices (spots: where POIs are), as far as they were asked for.

    A row is made by a search bounded by the distance that the asker needs, for several spots at a time, and
    keeps what lies on spots; so neither time nor memory is that of the whole network.
    """

    def __init__(self, net: Csr, spots: np.ndarray):
        self.net, self.spots = net, np.unique(spots)
        self.place = np.full(len(net.ids), -1, np.int32)
        self.place[self.spots] = np.arange(len(self.spots), dtype=np.int32)
        self.rows: OrderedDict[int, tuple[int, np.ndarray]] = OrderedDict()

    def __getstate__(self) -> dict:
        return self.__dict__ | {"rows": OrderedDict()}

    def between(self, a: int, b: int, limit: int, wanted: list[int]) -> int:
        """Distance of two spots; FAR or more if it exceeds the limit. wanted: spots that may be asked for next."""
        if a == b:
            return 0
        for u, v in ((a, b), (b, a)):
            if (row := self.rows.get(u)) is not None:
                d = int(row[1][self.place[v]])
                if d < FAR or row[0] >= limit:
                    return d
        return int(self._made(a, limit, wanted)[self.place[b]])

    def _made(self, a: int, limit: int, wanted: list[int]) -> np.ndarray:
        far = int(FAR) if limit >= FAR else limit + limit // 2
        most = max(1, min(64, WORK_BYTES // (8 * len(self.net.ids))))
        batch = [a]
        for v in wanted:
            if len(batch) == most:
                break
            if v != a and ((row := self.rows.get(v)) is None or row[0] < limit):
                batch.append(v)
        batch = list(dict.fromkeys(batch))
        found = self.net.many(np.array(batch), None if limit >= FAR else far)[:, self.spots]
        for v, row in zip(batch, found, strict=True):
            self.rows.pop(v, None)
            self.rows[v] = (far, row.copy())
        while len(self.rows) > max(most, KEPT_BYTES // (8 * max(1, len(self.spots)))):
            self.rows.popitem(last=False)
        return found[0]


def collect_csr(arcs: DataFrame, vertices: DataFrame | None = None, limit: int = LOCAL_ARCS) -> Csr:
    """The network on the driver, only if it has at most `limit` arcs."""
    rows = arcs.select("u", "v", "w").limit(limit + 1).toArrow()
    if rows.num_rows > limit:
        raise ValueError(f"more than {limit} arcs: use the wide mode")
    extra = vertices.select("v").toArrow().column("v").to_numpy() if vertices is not None else None
    return Csr(*(rows.column(c).to_numpy() for c in "uvw"), extra)


def sssp(arcs: DataFrame, sources: DataFrame, limit: int | None = None) -> DataFrame:
    """(s, v, dist) from every s of `sources`: sources are spread over tasks, each of which has the network as arrays, or a strip of a larger one."""
    spark = arcs.sparkSession
    if choose_mode(arcs, LOCAL_ARCS) == "wide":
        from .wide import sssp_strips

        return sssp_strips(arcs, sources, limit)
    net = spark.sparkContext.broadcast(collect_csr(arcs))

    def each(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        csr = net.value
        for b in batches:
            for s in b.column("s").to_pylist():
                r = None if s is None else csr.rank(s)
                if r is not None:
                    d = csr.distances(r, limit)
                    ok = d < FAR
                    yield pa.record_batch({"s": pa.array(np.full(ok.sum(), s)), "v": pa.array(csr.ids[ok]), "dist": pa.array(d[ok])})

    return sources.select("s").distinct().mapInArrow(each, "s long, v long, dist long")
