"""The search of one query over an index of arrays: explore, bound, prune, order."""

from __future__ import annotations

import bisect
import heapq
import math
from dataclasses import dataclass
from functools import cached_property, lru_cache
from itertools import permutations

import numpy as np

from ..distance.arrays import FAR, Csr, SpotRows
from ..index import dijkstra
from .spec import QuerySpec

SLACK = 2e-6  # scores are compared rounded to six digits
#: Tags up to which the orders of a set are listed.
MOST_LISTED = 8


@dataclass
class Arrays:
    """An index as arrays, by rank of vertex and of POI."""

    net: Csr
    x: np.ndarray
    y: np.ndarray
    cell: np.ndarray
    border: np.ndarray  # boolean
    shortcuts: dict[int, list[tuple[int, int]]]  # border -> other borders of its cell
    poi: np.ndarray
    poi_v: np.ndarray
    poi_rating: np.ndarray
    by_tag: dict[str, np.ndarray]
    personal: dict[int, dict[int, int]]
    w_max: float
    r_max: float
    ratio: float = 10.0
    overlay: Csr | None = None  # borders by rank of vertex: shortcuts and cross arcs
    #: Of a part of a network: numbers and best ratings of the query's tags over all of it, and (by None) its cells with a hit.
    whole: dict[str | None, tuple[int, int]] | None = None
    #: How far the last search settled, how far it had when it had k routes, and its first radius then.
    farthest: float = 0
    seeded: float = 0
    first_radius: float = 0

    def __post_init__(self) -> None:
        self.rows = SpotRows(self.net, self.poi_v) if self.net is not None else None

    def score(self, dist: float, rating: float, alpha: float) -> float:
        return round(-alpha * dist / self.w_max + (1 - alpha) * self.ratio * rating / self.r_max, 6)

    def bound(self, dist, rating, alpha: float):
        return -alpha * dist / self.w_max + (1 - alpha) * self.ratio * rating / self.r_max

    def radius(self, alpha: float, tau: float, floor: float | None) -> float:
        """Farthest that a route of ratings tau may go and still reach the floor."""
        if floor is None or alpha == 0:
            return math.inf
        return self.w_max * ((1 - alpha) * self.ratio * tau / self.r_max - floor + SLACK) / alpha

    def line(self, a, b, kind: str):
        """What no way between two vertices is shorter than."""
        if kind == "zero":
            return np.zeros(np.broadcast(a, b).shape)
        dx, dy = np.abs(self.x[a] - self.x[b]), np.abs(self.y[a] - self.y[b])
        return dx + dy if kind == "grid" else np.hypot(dx, dy)


@lru_cache(maxsize=4096)
def _orders(m: int, fixed: bool, before: tuple[tuple[int, int], ...]) -> tuple[tuple[int, ...], ...]:
    if fixed:
        return (tuple(range(m)),)
    return tuple(p for p in permutations(range(m)) if all(p.index(a) < p.index(b) for a, b in before))


class Hits:
    """The POIs of a query, by tag position."""

    def __init__(self, ix: Arrays, q: QuerySpec):
        self.lists, self.rating = [], {}
        own = ix.personal.get(q.user, {}) if q.user is not None else {}
        for tag in q.tags:
            found = ix.by_tag.get(tag, np.zeros(0, np.int64))
            rating = np.full(len(found), 50) if q.ratings == "identical" else np.array([own.get(int(ix.poi[p]), int(ix.poi_rating[p])) for p in found], np.int64)
            if q.rating_floor is not None:
                found, rating = found[rating >= q.rating_floor], rating[rating >= q.rating_floor]
            self.lists.append(found)
            self.rating |= dict(zip(((len(self.lists) - 1, int(p)) for p in found), rating.tolist(), strict=True))

    def of(self, j: int, p: int) -> int:
        return self.rating[j, p]


class Pool:
    """The k best routes: score downwards, then distance, then POIs in order of visit."""

    def __init__(self, k: int):
        self.k, self.rows = k, []

    def offer(self, score: float, dist: int, rating: int, pois: tuple[int, ...]) -> bool:
        row = (-score, dist, pois, rating)
        if len(self.rows) == self.k and row >= self.rows[-1] or row in self.rows:
            return False
        bisect.insort(self.rows, row)
        del self.rows[self.k :]
        return True

    @property
    def floor(self) -> float | None:
        return -self.rows[-1][0] if len(self.rows) == self.k else None

    def answers(self) -> list[tuple[int, float, int, int, list[int]]]:
        return [(i + 1, -s, d, r, list(p)) for i, (s, d, p, r) in enumerate(self.rows)]


class Legs:
    """Distances of a query's routes, and their orders."""

    def __init__(self, ix: Arrays, q: QuerySpec):
        self.ix, self.q = ix, q
        self.start = ix.net.rank(q.v_q)
        self.to_dest = None
        if q.dest is not None and (d := ix.net.rank(q.dest)) is not None:
            self.to_dest = ix.net.distances(d)
        place = {t: i for i, t in enumerate(q.tags)}
        self.before = tuple((place[a], place[b]) for a, b in q.precedence if a in place and b in place)
        #: Of many tags the best order of a set comes from its subsets, and no list of orders is made.
        self.by_subsets = len(q.tags) > MOST_LISTED and not q.order
        self.evaluated = 0
        #: What the exploration has seen: distances of POIs, how far it is, and the POIs' vertices.
        self.dist_of: dict[int, int] = {}
        self.seen_to: int | None = None
        self.wanted: list[int] = []

    @cached_property
    def orders(self) -> tuple[tuple[int, ...], ...]:
        return _orders(len(self.q.tags), self.q.order, self.before)

    @cached_property
    def order_array(self) -> np.ndarray:
        return np.array(self.orders, np.int64).reshape(-1, len(self.q.tags))

    @property
    def n_orders(self) -> int:
        """Orders of a cover set; of many tags, precedence is not taken off."""
        return math.factorial(len(self.q.tags)) if self.by_subsets else len(self.orders)

    def leg(self, at: int, p: int, limit: int = int(FAR)) -> int:
        """From the start or a POI's vertex to a POI; FAR or more if that exceeds the limit."""
        ix, v = self.ix, int(self.ix.poi_v[p])
        if at == self.start and (d := self.dist_of.get(p)) is not None:
            return d
        if ix.rows.place[at] < 0:
            return int(ix.net.distances(at)[v])
        return ix.rows.between(at, v, limit, self.wanted)

    def route(self, pois: list[int], longest: float = math.inf) -> int:
        """Length of a route; FAR if it exceeds the longest that counts, or has no way."""
        ix, at, total = self.ix, self.start, 0
        for p in pois:
            # two POIs seen from the start are no farther apart than the sum of their distances
            far = 2 * self.seen_to if self.seen_to is not None else math.inf
            left = min(longest - total, far)
            total += self.leg(at, p, int(left) + 1 if left < FAR else int(FAR))
            if total > longest:
                return int(FAR)
            at = int(ix.poi_v[p])
        total += int(self.to_dest[at]) if self.to_dest is not None else 0
        return min(total, int(FAR))

    def line_bounds(self, members: list[int]) -> np.ndarray:
        """Line length of every order of a set."""
        ix, v = self.ix, self.ix.poi_v[np.array(members)]
        kind = self.q.lower_bound
        between = ix.line(v[:, None], v[None, :], kind)
        first = ix.line(np.array(self.start), v, kind)
        o = self.order_array
        total = first[o[:, 0]] + between[o[:, :-1], o[:, 1:]].sum(1)
        return total + self.to_dest[v][o[:, -1]] if self.to_dest is not None else total

    def best_order(self, members: list[int], longest: float) -> tuple[int, tuple[int, ...]] | None:
        """Least (distance, POIs) over the orders: in order of line length, until that exceeds the best distance."""
        if self.by_subsets:
            return self._best_by_subsets(members, longest)
        lb = self.line_bounds(members)
        best: tuple[int, tuple[int, ...]] | None = None
        pick = np.argsort(lb, kind="stable") if "orders" in self.q.prune else np.arange(len(lb))
        for i in pick.tolist():
            if "orders" in self.q.prune and lb[i] > (longest if best is None else min(best[0], longest)) + 1e-6:
                break
            pois = [members[j] for j in self.orders[i]]
            d = self.route(pois, longest if best is None else min(best[0], longest))
            self.evaluated += 1
            found = (d, tuple(int(self.ix.poi[p]) for p in pois))
            if d < FAR and (best is None or found < best):
                best = found
        return best

    def _best_by_subsets(self, members: list[int], longest: float) -> tuple[int, tuple[int, ...]] | None:
        """The same, from the least (distance, POIs) of every subset and its last member."""
        ix, m = self.ix, len(members)
        v, names = [int(ix.poi_v[p]) for p in members], [int(ix.poi[p]) for p in members]
        needs = [sum(1 << a for a, b in self.before if b == j) for j in range(m)]
        limit = int(min(longest, 2 * self.seen_to if self.seen_to is not None else math.inf, int(FAR) - 1)) + 1
        step = [[self.leg(v[i], members[j], limit) if i != j else 0 for j in range(m)] for i in range(m)]
        layer = {(1 << j, j): (self.leg(self.start, members[j], limit), (names[j],)) for j in range(m) if not needs[j]}
        for _ in range(m - 1):
            grown: dict[tuple[int, int], tuple[int, tuple[int, ...]]] = {}
            for (mask, i), (d, said) in layer.items():
                for j in range(m):
                    if mask >> j & 1 or needs[j] & ~mask or d + step[i][j] > longest or d + step[i][j] >= FAR:
                        continue
                    found = (d + step[i][j], (*said, names[j]))
                    if (mask | 1 << j, j) not in grown or found < grown[mask | 1 << j, j]:
                        grown[mask | 1 << j, j] = found
            layer = grown
        self.evaluated += len(layer)
        ended = [(d + (int(self.to_dest[v[i]]) if self.to_dest is not None else 0), said) for (_, i), (d, said) in layer.items()]
        return min((x for x in ended if x[0] < FAR and x[0] <= longest), default=None)

    def walk(self, pois: list[int]) -> list[int]:
        """Vertices (by rank) of the route over POIs."""
        out, at = [self.start], self.start
        for v in [*(int(self.ix.poi_v[p]) for p in pois), *([self.ix.net.rank(self.q.dest)] if self.to_dest is not None else [])]:
            out += self.ix.net.path(at, v)[1:]
            at = v
        return out


def explore_and_bound(ix: Arrays, q: QuerySpec, trace: list | None = None) -> tuple[list, dict[str, int]]:
    """The k best cover routes: exact under every combination of prunings.

    Vertices settle in order of distance over the query graph (cells with hit POIs whole, other
    cells by shortcuts between their borders).  Every new hit POI makes cover sets with those seen.
    From k routes on, the k-th score is a floor: it bounds how far a POI may lie, which cells can
    still matter, which sets and which orders are worth a distance.
    """
    hits, legs, pool, m = Hits(ix, q), Legs(ix, q), Pool(q.k), len(q.tags)
    counters = dict.fromkeys(("cells_rn", "cells_sr", "cells_bp", "sets_sr", "sets_bp", "orders_sr", "orders_evaluated", "settled", "seeds"), 0)
    counters["sets_rn"] = math.prod(map(len, hits.lists))
    at_vertex: dict[int, list[tuple[int, int]]] = {}
    for j, found in enumerate(hits.lists):
        for p in found.tolist():
            at_vertex.setdefault(int(ix.poi_v[p]), []).append((j, p))
    live = {int(ix.cell[v]) for v in at_vertex}
    counters["cells_rn"] = len(live)
    ix.farthest = ix.seeded = ix.first_radius = 0
    if ix.whole is not None:
        counters["sets_rn"], counters["cells_rn"] = math.prod(ix.whole[t][0] for t in q.tags), ix.whole[None][0]
    if legs.start is None or not all(map(len, hits.lists)) or (q.dest is not None and legs.to_dest is None):
        return [], counters
    if q.dest is not None:
        live.add(int(ix.cell[ix.net.rank(q.dest)]))
    home = int(ix.cell[legs.start])
    net, alpha = ix.net, q.alpha
    tag_max = np.array([max(hits.of(j, int(p)) for p in found) for j, found in enumerate(hits.lists)])
    if ix.whole is not None:
        tag_max = np.array([ix.whole[t][1] for t in q.tags])
    cell_max: dict[int, np.ndarray] = {}
    cell_count: dict[int, np.ndarray] = {}
    for v, pois in at_vertex.items():
        best = cell_max.setdefault(int(ix.cell[v]), np.full(m, -(10**9)))
        count = cell_count.setdefault(int(ix.cell[v]), np.zeros(m, np.int64))
        for j, p in pois:
            best[j] = max(best[j], hits.of(j, p))
            count[j] += 1
    budget = math.inf if q.budget is None else q.budget
    state = {"tau": float(tag_max.sum()), "radius": budget, "maxima": tag_max}
    pruned: set[int] = set()
    bypassed: set[int] = set()  # pruned before any of its vertices was expanded
    touched: set[int] = set()
    first_at: dict[int, int] = {}

    inside_home: dict[int, list[tuple[int, int]]] = {}
    for u in np.flatnonzero(ix.cell == home).tolist():
        inside_home[u] = [(int(net.head[i]), int(net.w[i])) for i in range(net.ptr[u], net.ptr[u + 1]) if ix.cell[net.head[i]] == home]
    #: (border, distance inside the cell) of the start's cell
    exits = [(v, d) for v, d in dijkstra(inside_home, legs.start).items() if ix.border[v]]

    def near_cells(radius: float) -> list[tuple[int, int]]:
        """(nearest distance, cell) of live cells within the radius, the home cell at 0: a search over borders alone."""
        over = ix.overlay
        reach: dict[int, int] = {}
        if exits:
            rank = np.searchsorted(over.ids, [v for v, _ in exits])
            dist = over.reach(rank, np.array([d for _, d in exits], np.int64), int(radius) if radius < FAR else None)
            near = np.flatnonzero(dist < FAR)
            for d, c in zip(dist[near].tolist(), ix.cell[over.ids[near]].tolist(), strict=True):
                if c in cell_max and d < reach.get(c, FAR):
                    reach[c] = d
        if home in cell_max:
            reach[home] = 0
        return sorted((d, c) for c, d in reach.items())

    def fix_region() -> None:
        """Radius from the maxima of the cells within the radius, until neither moves."""
        floor = pool.floor
        radius = min(budget, ix.radius(alpha, float(tag_max.sum()), floor))
        ix.first_radius = ix.first_radius or radius
        cells = near_cells(radius)
        maxima = tag_max
        while True:
            inside = [c for d, c in cells if d <= radius]
            if trace is not None:
                trace.append((radius, len(inside), float(maxima.sum())))
            if not inside:
                break
            now = np.max([cell_max[c] for c in inside], axis=0)
            shrunk = min(budget, ix.radius(alpha, float(np.maximum(now, 0).sum()), floor))
            maxima = np.maximum(now, 0)
            if shrunk >= radius:
                break
            radius = shrunk
        counters["cells_sr"] = len(inside)
        counters["sets_sr"] = math.prod(int(x) for x in np.sum([cell_count[c] for c in inside], axis=0)) if inside else 0
        counters["orders_sr"] = counters["sets_sr"] * legs.n_orders
        state.update(tau=float(maxima.sum()), radius=radius, maxima=maxima if q.tau_scope == "region" else tag_max, cells=set(inside))

    def offered(members: list[int], rating: int) -> None:
        counters["sets_bp"] += 1
        floor = pool.floor
        whole = int(tag_max.sum()) if q.rating_scope == "path" else rating
        longest = min(budget, ix.radius(alpha, whole, floor)) if "sets" in q.prune else budget
        if q.route_scope == "per_set" and q.rating_scope == "set":
            best = legs.best_order(members, longest)
            if best and best[0] <= budget:
                pool.offer(ix.score(best[0], rating, alpha), best[0], rating, best[1])
            return
        lb = legs.line_bounds(members)
        best_of_set = None
        for i in np.argsort(lb, kind="stable").tolist():
            if "orders" in q.prune and lb[i] > longest + 1e-6:
                break
            pois = [members[j] for j in legs.orders[i]]
            d = legs.route(pois, longest)
            legs.evaluated += 1
            if d >= FAR or d > budget:
                continue
            r = rating
            if q.rating_scope == "path":
                best_by_tag: dict[int, int] = {}
                for v in legs.walk(pois):
                    for j, p in at_vertex.get(v, ()):
                        best_by_tag[j] = max(best_by_tag.get(j, 0), hits.of(j, p))
                r = sum(best_by_tag.values())
            row = (-ix.score(d, r, alpha), d, tuple(int(ix.poi[p]) for p in pois), r)
            if q.route_scope == "all_orders":
                pool.offer(-row[0], d, r, row[2])
            elif best_of_set is None or row < best_of_set:
                best_of_set = row
        if best_of_set:
            pool.offer(-best_of_set[0], best_of_set[1], best_of_set[3], best_of_set[2])

    lists: list[list[int]] = [[] for _ in range(m)]
    seen_max = [0] * m
    arrays: list[tuple[int, np.ndarray, np.ndarray, np.ndarray] | None] = [None] * m
    dist_of = legs.dist_of

    def columns(j: int) -> tuple[np.ndarray, np.ndarray, np.ndarray]:
        if arrays[j] is None or arrays[j][0] != len(lists[j]):
            p = np.array(lists[j], np.int64)
            far = np.array([dist_of[x] for x in lists[j]], np.int64)
            if legs.to_dest is not None:
                far = far + legs.to_dest[ix.poi_v[p]]
            arrays[j] = (len(lists[j]), p, np.array([hits.of(j, x) for x in lists[j]], np.int64), far)
        return arrays[j][1:]

    def stem(j: int, p: int) -> None:
        """Cover sets with a new POI, depth first from the best bounds on; partial sets are bounded too."""
        others = sorted((t for t in range(m) if t != j), key=lambda t: len(lists[t]))
        rest = [0] * (len(others) + 1)
        for i in range(len(others) - 1, -1, -1):
            rest[i] = rest[i + 1] + seen_max[others[i]]

        def grow(level: int, chosen: dict[int, int], rating: int, far: float) -> None:
            if level == len(others):
                offered([chosen[t] for t in range(m)], rating)
                return
            t = others[level]
            cand, cand_rating, cand_far = columns(t)
            total = rating + cand_rating + rest[level + 1]
            reach = np.maximum(cand_far, far).astype(float)
            floor = pool.floor
            if "sets" in q.prune and floor is not None:
                whole = np.full(len(cand), tag_max.sum()) if q.rating_scope == "path" else total
                keep = np.flatnonzero(ix.bound(reach, whole, alpha) >= floor - SLACK)
                if len(keep) and len(chosen) < 4 and q.lower_bound != "zero":
                    members = list(chosen)
                    v = [ix.poi_v[chosen[c]] for c in members]
                    vc = ix.poi_v[cand[keep]]
                    legs_lb = np.full(len(keep), np.inf)
                    spots = [*v, vc]
                    first = [ix.line(np.array(legs.start), x, q.lower_bound) for x in spots]
                    between = [[ix.line(x, y, q.lower_bound) if a < b else None for b, y in enumerate(spots)] for a, x in enumerate(spots)]
                    for o in permutations(range(len(spots))):
                        if q.order and [([*members, t])[i] for i in o] != sorted([*members, t]):
                            continue
                        length = first[o[0]]
                        for a, b in zip(o[:-1], o[1:], strict=True):
                            length = length + between[min(a, b)][max(a, b)]
                        legs_lb = np.minimum(legs_lb, length)
                    reach[keep] = np.maximum(reach[keep], legs_lb)
                    keep = keep[ix.bound(reach[keep], whole[keep], alpha) >= floor - SLACK]
            else:
                keep = np.arange(len(cand))
            value = ix.bound(reach, total, alpha)
            for i in keep[np.argsort(-value[keep], kind="stable")].tolist():
                floor = pool.floor
                if "sets" in q.prune and floor is not None and q.rating_scope == "set" and value[i] < floor - SLACK:
                    break
                grow(level + 1, chosen | {t: int(cand[i])}, rating + int(cand_rating[i]), float(reach[i]))

        far = dist_of[p] + (int(legs.to_dest[ix.poi_v[p]]) if legs.to_dest is not None else 0)
        grow(0, {j: p}, hits.of(j, p), float(far))

    # ---- exploration
    inner_of_start = [(v, d) for v, d in exits if v != legs.start] if home not in live else None

    def neighbours(u: int) -> list[tuple[int, int]]:
        c = int(ix.cell[u])
        arcs = [(int(net.head[i]), int(net.w[i])) for i in range(net.ptr[u], net.ptr[u + 1])]
        if c in live and c not in bypassed:
            return arcs
        if u == legs.start and inner_of_start is not None:
            return inner_of_start + [(v, w) for v, w in arcs if ix.cell[v] != c]
        if not ix.border[u]:
            return []
        return ix.shortcuts.get(u, []) + [(v, w) for v, w in arcs if ix.cell[v] != c]

    best, heap, done = {legs.start: 0}, [(0, legs.start)], set()
    started = False
    while heap:
        d, u = heapq.heappop(heap)
        if u in done:
            continue
        if d > state["radius"] + 1e-6 and ("region" in q.prune or q.budget is not None and d > budget):
            break
        done.add(u)
        ix.farthest = d
        c = int(ix.cell[u])
        if c in cell_max and c not in touched and pool.floor is not None and "cells" in q.prune:
            # first touch since there is a floor: can any route over a POI of this cell reach it?
            low = 0 if c == home else first_at.get(c, d) if q.cell_lb == "paper" else d
            maxima = state["maxima"]
            swap = np.where(cell_count[c] > 0, np.maximum(maxima - cell_max[c], 0), 10**9).min()
            if q.rating_scope == "path":
                swap = 0
            if c != home and ix.bound(low, float(maxima.sum() - swap), alpha) < pool.floor - SLACK:
                pruned.add(c)
                if c not in first_at:
                    bypassed.add(c)
            touched.add(c)
        first_at.setdefault(c, d)
        for j, p in () if c in pruned else at_vertex.get(u, ()):
            if legs.to_dest is not None and d + int(legs.to_dest[u]) > state["radius"] + 1e-6:
                continue
            dist_of[p], legs.seen_to = d, d
            legs.wanted.append(u)
            lists[j].append(p)
            seen_max[j] = max(seen_max[j], hits.of(j, p))
            if all(lists):
                before = pool.floor
                stem(j, p)
                if pool.floor is not None and not started:
                    started, ix.seeded = True, d
                    counters["seeds"] = counters["sets_bp"]
                    if "region" in q.prune:
                        fix_region()
                elif started and pool.floor != before and "region" in q.prune:
                    state["radius"] = min(state["radius"], ix.radius(alpha, state["tau"], pool.floor))
        for v, w in neighbours(u):
            if v not in done and d + w < best.get(v, FAR):
                best[v] = d + w
                heapq.heappush(heap, (d + w, v))
    counters["settled"] = len(done)
    counters["orders_evaluated"] = legs.evaluated
    if not started or "region" not in q.prune:
        counters["cells_sr"], counters["sets_sr"] = counters["cells_rn"], counters["sets_rn"]
        counters["orders_sr"] = counters["sets_sr"] * legs.n_orders
    counters["cells_bp"] = len([c for c in {int(ix.cell[x]) for x in done} if c in cell_max and c not in pruned])
    return pool.answers(), counters
