"""Queries over networks beyond one task, by any method: each gets the part of the network that its answers can lie in.

The network is packed into blocks of whole cells. Queries that start near each other go to one task, with the
blocks that come near enough to their starts. A search on such a part is right where what it found proves that nothing
farther off can matter; a query without that proof comes back with a wider radius. Coordinates must not
overstate distances, as everywhere in `search`.
"""

from __future__ import annotations

import math
import time
from dataclasses import replace

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from ..distance.arrays import FAR, Csr
from ..plans.mode import LOCAL_ARCS
from ..plans.rounds import materialize
from . import hops
from .search import Arrays
from .spec import QuerySpec

#: Vertices that a block has, about.
BLOCK = 4096
#: Sides of the square of blocks whose starts share a task, and queries that do, about; of large batches more, as each group is sent its blocks.
SQUARE, TOGETHER, GROUPS = 2, 16, 4096
_BLOCK_SCHEMA = "block long, bx long, by long, x0 long, x1 long, y0 long, y1 long, n_arcs long, part binary"
_ROW = "qid long, settled boolean, need double, rank int, score double, dist long, rating long, pois array<long>, counters map<string,long>, seconds double"


def _blocks(index, tags: DataFrame, side: int, shortcuts: bool) -> DataFrame:
    """One row a block: its box, and its vertices, arcs, POIs and shortcuts as a table in Arrow's format."""
    from ..network import arcs

    at = index.vertices.join(index.cells, "v").select("v", "x", "y", "cell")
    of_cell = at.groupBy("cell").agg(F.floor(F.min("x") / side).alias("bx"), F.floor(F.min("y") / side).alias("by"))
    home = materialize(at.join(of_cell, "cell").select("v", "x", "y", "cell", "bx", "by"), "placed")
    none = F.lit(None).cast("long")
    where = home.select(F.col("v").alias("a"), "bx", "by")
    rows = home.select("bx", "by", F.lit(0).alias("kind"), F.col("v").alias("a"), F.col("x").alias("b"), F.col("y").alias("c"), F.col("cell").alias("d"), F.lit(None).cast("string").alias("tag"))
    rows = rows.unionByName(arcs(index.edges).join(where.withColumnRenamed("a", "u"), "u").select("bx", "by", F.lit(1).alias("kind"), F.col("u").alias("a"), F.col("v").alias("b"), F.col("w").cast("long").alias("c"), none.alias("d"), F.lit(None).cast("string").alias("tag")))
    pois = index.pois.join(F.broadcast(tags), "tag", "left_semi")  # tags that are asked for
    rows = rows.unionByName(pois.join(where.withColumnRenamed("a", "v"), "v").select("bx", "by", F.lit(2).alias("kind"), F.col("poi").alias("a"), F.col("v").alias("b"), F.col("rating").cast("long").alias("c"), none.alias("d"), "tag"))
    if shortcuts:
        rows = rows.unionByName(index.shortcuts.join(where.withColumnRenamed("a", "u"), "u").select("bx", "by", F.lit(3).alias("kind"), F.col("u").alias("a"), F.col("v").alias("b"), F.col("dist").cast("long").alias("c"), none.alias("d"), F.lit(None).cast("string").alias("tag")))

    def pack(key: tuple[pa.Scalar, ...], table: pa.Table) -> pa.Table:
        kind = table.column("kind").to_numpy()
        x, y = table.column("b").to_numpy()[kind == 0], table.column("c").to_numpy()[kind == 0]
        sink = pa.BufferOutputStream()
        body = table.select(["kind", "a", "b", "c", "d", "tag"]).combine_chunks()
        with pa.ipc.new_stream(sink, body.schema, options=pa.ipc.IpcWriteOptions(compression="zstd")) as out:
            out.write_table(body)
        bx, by = key[0].as_py(), key[1].as_py()
        one = [[(bx << 31) + by], [bx], [by], [int(x.min())], [int(x.max())], [int(y.min())], [int(y.max())], [int((kind == 1).sum())], [sink.getvalue().to_pybytes()]]
        return pa.table([pa.array(c, t) for c, t in zip(one, [*[pa.int64()] * 8, pa.binary()], strict=True)], ["block", "bx", "by", "x0", "x1", "y0", "y1", "n_arcs", "part"])

    return materialize(rows.groupBy("bx", "by").applyInArrow(pack, _BLOCK_SCHEMA), "blocks")


class _Shortcuts:
    """Shortcuts by border, as arrays."""

    def __init__(self, u: np.ndarray, v: np.ndarray, d: np.ndarray):
        order = np.argsort(u, kind="stable")
        self.u, self.v, self.d = u[order], v[order], d[order]

    def get(self, at: int, default: list) -> list[tuple[int, int]]:
        i, j = np.searchsorted(self.u, [at, at + 1])
        return list(zip(self.v[i:j].tolist(), self.d[i:j].tolist(), strict=True)) if j > i else default


def _arrays(parts: list[bytes], w_max: float, r_max: float, ratio: float) -> Arrays:
    """A part of the network; arcs that leave it go."""
    if parts:
        t = pa.concat_tables([pa.ipc.open_stream(p).read_all() for p in parts])
    else:
        t = pa.table({**{c: pa.array([], pa.int64()) for c in ("kind", "a", "b", "c", "d")}, "tag": pa.array([], pa.string())})
    kind = t.column("kind").to_numpy()
    of = lambda k: (rows := t.filter(pa.array(kind == k))) and [rows.column(c).to_numpy() for c in "abcd"[: 4 if k == 0 else 3]]
    v, x, y, cell = of(0) or [np.zeros(0, np.int64)] * 4
    u, w, d = of(1) or [np.zeros(0, np.int64)] * 3
    whole = np.sort(v)
    known = lambda a: (whole[np.minimum(np.searchsorted(whole, a), len(whole) - 1)] == a) if len(whole) else np.zeros(len(a), bool)
    ok = known(w)
    net = Csr(u[ok], w[ok], d[ok], whole)
    order = np.argsort(v, kind="stable")
    x, y, cell = x[order], y[order], cell[order]
    tail = np.repeat(np.arange(len(net.ids)), np.diff(net.ptr))
    crossing = cell[tail] != cell[net.head] if len(tail) else np.zeros(0, bool)
    su, sv, sd = of(3) or [np.zeros(0, np.int64)] * 3
    border = np.zeros(len(net.ids), bool)
    border[tail[crossing]] = True
    leaving = u[~ok]
    border[np.searchsorted(net.ids, leaving)] = True
    su, sv = np.searchsorted(net.ids, su), np.searchsorted(net.ids, sv)
    overlay = Csr(np.concatenate((su, tail[crossing])), np.concatenate((sv, net.head[crossing])), np.concatenate((sd, net.w[crossing])), np.flatnonzero(border))
    p = t.filter(pa.array(kind == 2)).sort_by([("a", "ascending"), ("tag", "ascending")])
    tags = np.array(p.column("tag").to_pylist(), object)
    by_tag = {name: np.flatnonzero(tags == name) for name in set(tags.tolist())}
    return Arrays(net, x, y, cell, border, _Shortcuts(su, sv, sd), p.column("a").to_numpy(), np.searchsorted(net.ids, p.column("b").to_numpy()), p.column("c").to_numpy(), by_tag, {}, w_max, r_max, ratio, overlay)


def _cut(ix: Arrays, q: QuerySpec, radius: float) -> Arrays:
    """What lies on ways from the start (to the destination) of the radius at most, for methods that know no region."""
    start, dest = ix.net.rank(q.v_q), ix.net.rank(q.dest) if q.dest is not None else None
    if start is None or q.dest is not None and dest is None:
        return ix
    limit = None if radius >= FAR else int(radius) + 1
    far = ix.net.reach(np.array([start]), np.array([0]), limit)
    if dest is not None:
        far = np.minimum(far + ix.net.reach(np.array([dest]), np.array([0]), limit), FAR)
    keep = (far < FAR) & (far <= (FAR if limit is None else limit))
    keep[[start, *([dest] if dest is not None else [])]] = True
    tail = np.repeat(np.arange(len(ix.net.ids)), np.diff(ix.net.ptr))
    ok = keep[tail] & keep[ix.net.head]
    net = Csr(ix.net.ids[tail[ok]], ix.net.ids[ix.net.head[ok]], ix.net.w[ok], ix.net.ids[keep])
    some = keep[ix.poi_v]
    place = np.cumsum(some) - 1
    by_tag = {t: place[found[some[found]]] for t, found in ix.by_tag.items()}
    return Arrays(net, ix.x[keep], ix.y[keep], ix.cell[keep], ix.border[keep], {}, ix.poi[some], np.searchsorted(net.ids, ix.net.ids[ix.poi_v[some]]), ix.poi_rating[some], by_tag, ix.personal, ix.w_max, ix.r_max, ix.ratio)


def _need(ix: Arrays, q: QuerySpec, method: str, rows: list, numbers: list[int], best: list[int]) -> float | None:
    """How far the network must be known for these answers to be right; None if they don't tell."""
    m, tau = len(q.tags), sum(best)
    if method.startswith("greedy"):
        return _greedy_need(ix, q, method, rows, best)
    k = 1 if method == "budget_labels" else q.k
    routes = math.prod(numbers) * (math.factorial(m) if q.route_scope == "all_orders" and not q.order else 1)
    budget = math.inf if q.budget is None else float(q.budget)
    if len(rows) >= k:
        return min(budget, ix.radius(q.alpha, tau, rows[k - 1][1]))
    if len(rows) == routes and not q.precedence and q.budget is None:
        return float(max(r[2] for r in rows))
    return budget if budget < math.inf else None


def _counted_need(ix: Arrays, q: QuerySpec, need: float) -> float:
    """How far the network must be known for the search's counters to be right, too.

    A route that leaves what is known is longer than that. From k routes on, routes beyond the first radius are dropped
    whatever their length; those before go no farther than twice what was settled by then.
    """
    usual = {"region", "sets"} <= q.prune and q.dest is None and q.rating_scope == "set" and ix.first_radius > 0
    return max(need, 2.0 * (ix.seeded if usual else ix.farthest), ix.first_radius)


def _on_to_dest(ix: Arrays, q: QuerySpec, radius: float, more: float) -> float | None:
    """Where answers lacked: a radius with room for some way beside the one to the destination; None if that is no wider."""
    start, dest = ix.net.rank(q.v_q), ix.net.rank(q.dest)
    if start is None or dest is None:
        return None
    far = int(ix.net.reach(np.array([start]), np.array([0]), None)[dest])
    return far + more if far < FAR and far + more > radius + more / 2 else None


def _greedy_need(ix: Arrays, q: QuerySpec, method: str, rows: list, best: list[int]) -> float | None:
    """A hop is right if all within its length of where it begins is known, and (by rating) no open tag has a better place anywhere."""
    from .search import Hits

    if not rows:
        return None
    hits, net = Hits(ix, q), ix.net
    spot, open_tags, start = net.rank(q.v_q), set(range(len(q.tags))), net.rank(q.v_q)
    at, need = spot, 0.0
    name = {int(p): i for i, p in enumerate(ix.poi)}
    of_name: dict[int, list[int]] = {}
    for i, p in enumerate(ix.poi.tolist()):
        of_name.setdefault(p, []).append(i)
    for poi in rows[0][4]:
        taken = [(j, p) for j in sorted(open_tags) for p in of_name.get(poi, [name[poi]]) if (j, p) in hits.rating and (not q.order or j == min(open_tags))]
        if method == "greedy_rating" and hits.of(*taken[0]) < max(best[j] for j in (open_tags if not q.order else [min(open_tags)])):
            return None
        j, p = taken[0]
        v = int(ix.poi_v[p])
        leg = int(net.distances(at)[v])
        need = max(need, float(ix.line(np.array(start), np.array(at), "euclid")) + leg)
        open_tags.discard(j)
        at = v
    if q.dest is not None:
        need = max(need, float(rows[0][2]))
    return need


def run_regions(index, queries: DataFrame, method: str, variant: dict, counters: bool = False, limit: int = LOCAL_ARCS) -> DataFrame:
    """Answers, or counters and seconds, of a batch; ValueError if a query's part of the network has more than `limit` arcs."""
    from .wide import _hits

    spark = queries.sparkSession
    user = variant.get("user")
    own = index.own(user) if user is not None else {}
    given = {n: v for n, v in variant.items() if n in ("v_q", "alpha", "k", "dest", "budget")}
    asked = queries.withColumns({n: F.lit(v).cast(queries.schema[n].dataType) for n, v in given.items()}) if given else queries
    asked = asked.select("qid", "v_q", F.array_distinct("tags").alias("tags"), "alpha", "k", "dest", "budget").filter("v_q is not null and size(tags) > 0")
    asked = materialize(asked, "asked")
    tags = asked.select(F.explode("tags").alias("tag")).distinct()
    # numbers and best ratings of each tag over the whole network; for counters, cells with a hit too
    one = tags.select(F.xxhash64("tag").alias("qid"), F.array("tag").alias("tags"))
    placed = index.pois.join(index.cells, "v").select("tag", "poi", "v", "cell", "rating")
    kind = (index.personal, variant.get("ratings", "given"), user, variant.get("rating_floor"))
    if method == "greedy_rating" and not counters:  # the best rated places lie anywhere
        return hops.greedy_rating(index, asked, _hits(placed, asked, *kind), variant.get("order", False))
    found = _hits(placed, one, *kind)
    per_tag = found.groupBy("qid").agg(F.count("*").alias("n"), F.max("rating").alias("best")).join(one.select("qid", F.col("tags")[0].alias("tag")), "qid").select("tag", "n", "best")
    told = asked.select("qid", F.posexplode("tags").alias("pos", "tag")).join(F.broadcast(per_tag), "tag", "left")  # a row a tag
    told = told.groupBy("qid").agg(F.transform(F.array_sort(F.collect_list(F.struct("pos", F.coalesce("n", F.lit(0)).alias("n"), F.coalesce("best", F.lit(0)).alias("best")))), lambda x: F.struct(x["n"].alias("n"), x["best"].alias("best"))).alias("whole"))
    if counters:
        live = found.select(F.col("qid").alias("t"), "cell").distinct()
        cells = asked.select("qid", F.explode("tags").alias("tag")).select("qid", F.xxhash64("tag").alias("t")).join(live, "t").select("qid", "cell").distinct().groupBy("qid").agg(F.count("*").alias("cells_rn"))
        told = told.join(cells, "qid", "left")
    else:
        told = told.withColumn("cells_rn", F.lit(0).cast("long"))
    box = index.vertices.agg(F.min("x").alias("x0"), F.max("x").alias("x1"), F.min("y").alias("y0"), F.max("y").alias("y1"), F.count("*").alias("n")).first()
    empty = spark.createDataFrame([], _ROW)
    if not box.n:
        return empty
    area = max(1.0, float(box.x1 - box.x0 + 1) * float(box.y1 - box.y0 + 1))
    side = max(1, int(math.sqrt(area / box.n * BLOCK)))
    blocks = _blocks(index, tags, side, shortcuts=method == "ebs")
    boxes = materialize(blocks.drop("part"), "boxes")
    n_blocks = boxes.count()
    xy = index.vertices.select("v", "x", "y")
    spots = asked.join(told, "qid").join(xy.select(F.col("v").alias("v_q"), F.col("x").cast("double").alias("sx"), F.col("y").cast("double").alias("sy")), "v_q", "left")
    spots = spots.join(xy.select(F.col("v").alias("dest"), F.col("x").cast("double").alias("dx"), F.col("y").cast("double").alias("dy")), "dest", "left")
    # a first radius: where some places of the rarest tag are likely, or twice the line to the destination
    rarest = F.array_min(F.transform("whole", lambda x: x["n"]))
    guess = F.when(rarest > 0, 2 * F.sqrt(F.size("tags") * F.lit(area) / rarest)).otherwise(0.0)
    line = F.coalesce(F.hypot(F.col("sx") - F.col("dx"), F.col("sy") - F.col("dy")), F.lit(0.0))
    waiting = spots.withColumn("guess", guess).withColumn("r", F.least(F.coalesce(F.col("budget").cast("double"), F.lit(1e18)), F.greatest(guess, 1.5 * line)))
    if method == "greedy_rating":
        waiting = waiting.withColumn("r", F.lit(3.0) * guess)
    elif counters and method == "ebs":  # counters ask for more than answers
        waiting = waiting.withColumn("r", F.least(F.coalesce(F.col("budget").cast("double"), F.lit(1e18)), 1.5 * F.col("r")))
    waiting = materialize(waiting, "waiting")
    scale = (index.w_max, index.r_max, index.ratio)
    rest = {n: v for n, v in variant.items() if n not in given}

    def answer(key: tuple[pa.Scalar, ...], left: pa.Table, right: pa.Table) -> pa.Table:
        from ..baselines.local import METHODS

        parts = [p for p in right.column("part").to_pylist() if p is not None]
        ix, out = _arrays(parts, *scale), []
        ix.personal = {user: own} if user is not None else {}
        for q in left.to_pylist():
            spec = QuerySpec(qid=q["qid"], v_q=q["v_q"], tags=tuple(q["tags"]), alpha=q["alpha"], k=q["k"], dest=q["dest"], budget=q["budget"], **rest)
            numbers, best, radius = [x["n"] for x in q["whole"]], [int(x["best"]) for x in q["whole"]], q["r"]
            part = ix if method == "ebs" else _cut(ix, spec, radius)
            part.whole = {t: (n, b) for t, n, b in zip(q["tags"], numbers, best, strict=True)} | {None: (q["cells_rn"] or 0, 0)}
            began = time.perf_counter()
            free = replace(spec, budget=None) if method.startswith("greedy") else spec
            rows, counted = METHODS[method](part, free)
            took = time.perf_counter() - began
            complete = len(parts) == n_blocks or q["sx"] is None or q["dest"] is not None and q["dx"] is None or not all(numbers)
            need = math.inf if complete else _need(part, free, method, rows, numbers, best)
            if need is not None and not complete and counters and method == "ebs":
                need = _counted_need(part, spec, need)
            if method.startswith("greedy") and spec.budget is not None:
                rows = [r for r in rows if r[2] <= spec.budget]
            settled = complete or need is not None and need <= radius
            if need is None and spec.dest is not None:
                need = _on_to_dest(ix, spec, radius, q["guess"] / 2)
            if not settled:
                out.append((q["qid"], False, need, None, None, None, None, None, None, None))
            elif counters:
                out.append((q["qid"], True, None, None, None, None, None, None, list(counted.items()), took))
            else:
                out += [(q["qid"], True, None, *r, None, None) for r in rows]
        c = list(zip(*out, strict=True)) or [[]] * 10
        types = [pa.int64(), pa.bool_(), pa.float64(), pa.int32(), pa.float64(), pa.int64(), pa.int64(), pa.list_(pa.int64()), pa.map_(pa.string(), pa.int64()), pa.float64()]
        return pa.table([pa.array(list(x), t) for x, t in zip(c, types, strict=True)], ["qid", "settled", "need", "rank", "score", "dist", "rating", "pois", "counters", "seconds"])

    done = empty
    while True:
        squares = _squares(waiting, side * SQUARE)
        near = _near(squares, boxes)
        if _most(near) > limit:  # then every query by itself
            squares = waiting.withColumn("g", F.col("qid").cast("string"))
            near = _near(squares, boxes)
            if (most := _most(near)) > limit:
                raise ValueError(f"a query's part of the network has {most} arcs, more than the {limit} that go to a task")
        # a group has its blocks once; of a group without any, the queries alone
        sent = near.select("g", "block").join(blocks.select("block", "part"), "block").select(F.col("g").alias("to"), "part")
        # groups are few and dear, so the number of tasks is ours and not left to their bytes
        n = min(2 * squares.select("g").distinct().count(), 1024)
        got = materialize(squares.repartition(n, "g").groupBy("g").cogroup(sent.repartition(n, "to").groupBy("to")).applyInArrow(answer, _ROW), "answers")
        done = done.unionByName(got.filter("settled"))
        left = got.filter("not settled").select("qid", "need")
        if left.isEmpty():
            break
        # known needs get their radius with some slack, others half as much again
        waiting = materialize(waiting.join(left, "qid").withColumn("r", F.greatest(F.coalesce(F.col("need") + 2, F.lit(0.0)), F.when(F.col("need").isNull(), 1.5 * F.col("r")).otherwise(F.col("r") + 1))).drop("need"), "waiting")
    return done.select("qid", "counters", "seconds") if counters else done.select("qid", "rank", "score", "dist", "rating", "pois")


def _squares(waiting: DataFrame, width: int) -> DataFrame:
    """Queries with their group g: the square of their starts, and a part of it where many start there."""
    at = waiting.withColumn("square", F.concat_ws(":", *(F.floor(F.coalesce(c, F.lit(0.0)) / width).cast("string") for c in ("sx", "sy"))))
    together = max(TOGETHER, -(-waiting.count() // GROUPS))
    parts = at.groupBy("square").agg(F.ceil(F.count("*") / together).alias("parts"))
    return at.join(parts, "square").withColumn("g", F.concat_ws("/", "square", F.pmod(F.xxhash64("qid"), F.col("parts")).cast("string"))).drop("square", "parts")


def _most(near: DataFrame) -> int:
    return near.groupBy("g").agg(F.sum("n_arcs").alias("n")).agg(F.max("n")).first()[0] or 0


def _near(squares: DataFrame, boxes: DataFrame) -> DataFrame:
    """(g, block, n_arcs): blocks on ways of each group's queries, by the line to the start and on to the destination."""
    gap = lambda lo, hi, at: F.greatest(F.col(lo) - F.col(at), F.col(at) - F.col(hi), F.lit(0.0))
    off = F.hypot(gap("x0", "x1", "sx"), gap("y0", "y1", "sy"))
    on = F.coalesce(F.hypot(gap("x0", "x1", "dx"), gap("y0", "y1", "dy")), F.lit(0.0))
    pairs = squares.filter("sx is not null").select("g", "sx", "sy", "dx", "dy", "r").join(F.broadcast(boxes), (off <= F.col("r")) & (off + on <= F.col("r")))  # a row a block
    return pairs.select("g", "block", "n_arcs").distinct()
