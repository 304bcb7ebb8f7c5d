"""Distances by DataFrame rounds over cells: a round crosses one cell, whatever its size."""

from __future__ import annotations

from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

from ..plans.rounds import discard, materialize


def sssp_wide(closed: DataFrame, cross: DataFrame, cells: DataFrame, sources: DataFrame, limit: int | None = None, max_rounds: int = 10_000) -> DataFrame:
    """(s, v, dist) from every s of `sources`, over cell distances (full level) and cross edges.

    Only vertices that improved go on. Each round is written to the shared folder, so a lost
    executor costs a round's retry. `limit` keeps distances up to it, and makes rounds few.
    """
    steps = cross.select("u", "v", "w").unionByName(cross.select(F.col("v").alias("u"), F.col("u").alias("v"), "w"))
    inside = closed.select("u", "v", F.col("dist").alias("w"))
    within = (lambda df: df.filter(F.col("dist") <= limit)) if limit is not None else (lambda df: df)

    def spread(front: DataFrame, over: DataFrame) -> DataFrame:
        return within(front.select("s", F.col("v").alias("u"), "dist").join(over, "u").select("s", "v", (F.col("dist") + F.col("w")).alias("dist"))).groupBy("s", "v").agg(F.min("dist").alias("dist"))

    front = sources.select("s").distinct().select("s", F.col("s").alias("v"), F.lit(0).cast("long").alias("dist"))
    known = materialize(spread(front, inside), "reached")
    front = known
    for _ in range(max_rounds):
        entered = spread(front, steps)
        better = spread(entered, inside).join(known.withColumnRenamed("dist", "old"), ["s", "v"], "left").filter(F.col("old").isNull() | (F.col("dist") < F.col("old"))).select("s", "v", "dist")
        better = materialize(better, "front")
        if better.isEmpty():
            return known
        before = known
        known = materialize(known.unionByName(better).groupBy("s", "v").agg(F.min("dist").alias("dist")), "reached")
        discard(before, *([front] if front is not before else []))
        front = better
    raise RuntimeError("distances did not settle")


def same_cell_true(closed: DataFrame, cross: DataFrame, cells: DataFrame, border: DataFrame) -> DataFrame:
    """(cell, u, v, dist): cell distances repaired by ways that leave the cell and come back, over all of the cell's borders.

    Distances between borders of a cell over the whole network come from rounds; a pair's true
    distance is the least of the inner one and those through two borders.
    """
    over = sssp_wide(closed, cross, cells, border.select(F.col("v").alias("s")).distinct())
    of_cell = border.select("cell", F.col("v").alias("b1")).join(border.select("cell", F.col("v").alias("b2")), "cell")
    loops = of_cell.join(over.select(F.col("s").alias("b1"), F.col("v").alias("b2"), F.col("dist").alias("d")), ["b1", "b2"]).select("cell", "b1", "b2", "d")
    out = closed.select("cell", "u", F.col("v").alias("b1"), F.col("dist").alias("d1")).join(loops, ["cell", "b1"]).groupBy("cell", "u", "b2").agg(F.min(F.col("d1") + F.col("d")).alias("d2"))
    back = out.join(closed.select("cell", F.col("u").alias("b2"), "v", F.col("dist").alias("d3")), ["cell", "b2"]).groupBy("cell", "u", "v").agg(F.min(F.col("d2") + F.col("d3")).alias("through"))
    both = back.join(closed, ["cell", "u", "v"], "full")
    return both.select("cell", "u", "v", F.least("through", "dist").alias("dist"))


def sssp_strips(arcs: DataFrame | Strips, sources: DataFrame, limit: int | None = None, most: int = 1_000_000, max_rounds: int = 10_000, targets: DataFrame | None = None) -> DataFrame:
    """(s, v, dist) from every s of `sources` over any arcs, by strips of vertices with about `most` arcs each.

    targets (s, v): only these are told; sources are then not looked up among the arcs' ends first.

    A task holds one strip as arrays, and settles all of it from the distances at which its vertices are entered from other
    strips. A round crosses a strip; only entries that improved go on, and interiors are told once, at the end.
    """
    import numpy as np
    import pyarrow as pa

    from .arrays import FAR, Csr

    net = arcs if isinstance(arcs, Strips) else Strips(arcs, most)
    low, size, chosen = net.low, net.size, targets is not None
    starts = sources.select("s").distinct()
    starts = starts if chosen else net.known(starts)

    def settle(inner: bool):
        def each(key: tuple[pa.Scalar, ...], front: pa.Table, part: pa.Table) -> pa.Table:
            u, v, w = net.unpack(part)
            a = low + key[0].as_py() * size
            home = (v >= a) & (v < a + size)
            own, told = front.column("v").to_numpy(), front.column("dist").is_valid().to_numpy(zero_copy_only=False)
            csr = Csr(u[home], v[home], w[home], np.concatenate((u, own)))
            out = []
            s, d = front.column("s").to_numpy(), front.column("dist").fill_null(0).to_numpy()
            for one in np.unique(s[told]):
                mine = (s == one) & told
                dist = csr.reach(np.searchsorted(csr.ids, own[mine]), d[mine], limit)
                if inner and chosen:
                    at = np.searchsorted(csr.ids, own[(s == one) & ~told])
                    at = at[dist[at] < FAR]
                    out.append((np.full(len(at), one), csr.ids[at], dist[at]))
                elif inner:
                    ok = dist < FAR
                    out.append((np.full(ok.sum(), one), csr.ids[ok], dist[ok]))
                else:
                    far = dist[np.searchsorted(csr.ids, u[~home])]
                    ok = (far < FAR) & (far + w[~home] <= (FAR if limit is None else limit))
                    out.append((np.full(ok.sum(), one), v[~home][ok], (far + w[~home])[ok]))
            c = [np.concatenate(x) for x in zip(*out, strict=True)] or [np.zeros(0, np.int64)] * 3
            return pa.table({"s": pa.array(c[0], pa.int64()), "v": pa.array(c[1], pa.int64()), "dist": pa.array(c[2], pa.int64())})

        return each

    def over(front: DataFrame, inner: bool) -> DataFrame:
        at = front.select("s", "v", "dist", net.strip("v").alias("of"))
        part = net.parts.join(at.select(F.col("of").alias("strip")).distinct(), "strip", "left_semi")
        # strips are few and dear, so the number of tasks is ours and not left to their bytes
        return at.repartition(net.tasks, "of").groupBy("of").cogroup(part.repartition(net.tasks, "strip").groupBy("strip")).applyInArrow(settle(inner), "s long, v long, dist long")

    entries = front = materialize(starts.select("s", F.col("s").alias("v"), F.lit(0).cast("long").alias("dist")), "entries")
    for _ in range(max_rounds):
        entered = over(front, False).groupBy("s", "v").agg(F.min("dist").alias("dist"))
        better = materialize(entered.join(entries.withColumnRenamed("dist", "old"), ["s", "v"], "left").filter("old is null or dist < old").select("s", "v", "dist"), "front")
        if better.isEmpty():
            return over(entries.unionByName(targets.select("s", "v", F.lit(None).cast("long").alias("dist")).distinct()) if chosen else entries, True)
        before = entries
        entries = materialize(entries.unionByName(better).groupBy("s", "v").agg(F.min("dist").alias("dist")), "entries")
        discard(before, *([front] if front is not before else []))
        front = better
    raise RuntimeError("distances did not settle")


class Strips:
    """Arcs by strips of their tails, about `most` to a strip, packed once for several searches: `parts` (strip, part)."""

    def __init__(self, arcs: DataFrame, most: int = 1_000_000):
        import pyarrow as pa

        all_of = arcs.agg(F.count("*").alias("n"), F.least(F.min("u"), F.min("v")).alias("a"), F.greatest(F.max("u"), F.max("v")).alias("b")).first()
        wide = (all_of.b - all_of.a + 1) if all_of.n else 1
        self.low, self.size = all_of.a or 0, max(1, -(-wide * most // max(all_of.n, most)))
        self.tasks = min(1024, 4 * -(-wide // self.size))

        def pack(key: tuple[pa.Scalar, ...], table: pa.Table) -> pa.Table:
            sink = pa.BufferOutputStream()
            body = table.select(["u", "v", "w"]).combine_chunks()
            with pa.ipc.new_stream(sink, body.schema, options=pa.ipc.IpcWriteOptions(compression="zstd")) as out:
                out.write_table(body)
            return pa.table({"strip": pa.array([key[0].as_py()], pa.int64()), "part": pa.array([sink.getvalue().to_pybytes()], pa.binary())})

        rows = arcs.select("u", "v", F.col("w").cast("long").alias("w"), self.strip("u").alias("strip"))
        self.arcs, self.parts = arcs, materialize(rows.repartition(self.tasks, "strip").groupBy("strip").applyInArrow(pack, "strip long, part binary"), "strips")

    def __getstate__(self) -> dict:
        return {"low": self.low, "size": self.size}

    def strip(self, c: str) -> Column:
        return F.floor((F.col(c) - self.low) / self.size)

    def known(self, sources: DataFrame) -> DataFrame:
        """Sources (s) that are ends of arcs."""
        ends = self.arcs.select(F.col("u").alias("s")).unionByName(self.arcs.select(F.col("v").alias("s")))
        return sources.join(ends, "s", "left_semi")

    @staticmethod
    def unpack(part) -> list:
        """Tails, heads and lengths of a strip's arcs, as arrays."""
        import numpy as np
        import pyarrow as pa

        if not part.num_rows:
            return [np.zeros(0, np.int64)] * 3
        body = pa.ipc.open_stream(part.column("part")[0].as_py()).read_all()
        return [body.column(c).to_numpy() for c in "uvw"]
