"""Competing searches over the same index: each takes (index, query) and returns answers and counters."""

from __future__ import annotations

import heapq
import math
from collections.abc import Callable
from itertools import product

import numpy as np

from ..distance.arrays import FAR, WORK_BYTES
from ..query.search import SLACK, Arrays, Hits, Legs, Pool, explore_and_bound
from ..query.spec import QuerySpec


class _Legwork:
    """Distances between start, hit POIs and destination, by lists of candidates."""

    def __init__(self, ix: Arrays, q: QuerySpec):
        self.ix, self.q, self.hits, self.legs = ix, q, Hits(ix, q), Legs(ix, q)
        self.ok = self.legs.start is not None and all(map(len, self.hits.lists)) and (q.dest is None or self.legs.to_dest is not None)
        self.lists = [[int(p) for p in found] for found in self.hits.lists]
        self.tau = sum(max(self.hits.of(j, p) for p in found) for j, found in enumerate(self.lists)) if self.ok else 0
        self.budget = FAR if q.budget is None else q.budget
        self.counters = {"labels": 0, "routes": 0}
        self.legs.wanted = [int(v) for v in dict.fromkeys(int(self.ix.poi_v[p]) for found in self.lists for p in found)]

    def leg(self, at: int, p: int) -> int:
        """From a vertex to a POI; FAR or more if that exceeds the budget."""
        return min(self.legs.leg(at, p, int(self.budget)), int(FAR))

    def home(self, p: int) -> int:
        return int(self.legs.to_dest[self.ix.poi_v[p]]) if self.legs.to_dest is not None else 0

    def names(self, pois: tuple[int, ...]) -> tuple[int, ...]:
        return tuple(int(self.ix.poi[p]) for p in pois)


#: Routes up to which all are listed one by one.
MOST_ROUTES = 2_000_000


def exhaustive(ix: Arrays, q: QuerySpec) -> tuple[list, dict[str, int]]:
    """Every order of every cover set; of more than MOST_ROUTES routes, those that share a beginning are judged together."""
    g, pool = _Legwork(ix, q), Pool(q.k)
    if not g.ok:
        return [], g.counters
    if math.prod(map(len, g.lists)) * g.legs.n_orders > MOST_ROUTES:
        return _by_completions(ix, q, g, pool)
    for members in product(*g.lists):
        rating = sum(g.hits.of(j, p) for j, p in enumerate(members))
        best = None
        for order in g.legs.orders:
            pois = [members[j] for j in order]
            d = g.legs.route(pois)
            g.counters["routes"] += 1
            if d >= FAR or d > g.budget:
                continue
            row = (d, g.names(tuple(pois)))
            if q.route_scope == "all_orders":
                pool.offer(ix.score(d, rating, q.alpha), d, rating, row[1])
            elif best is None or row < best:
                best = row
        if best:
            pool.offer(ix.score(best[0], rating, q.alpha), best[0], rating, best[1])
    return pool.answers(), g.counters


def _by_completions(ix: Arrays, q: QuerySpec, g: _Legwork, pool: Pool) -> tuple[list, dict[str, int]]:
    """The same answers: for each order, the best completion from every POI, and from the start all routes that the k-th score leaves open.

    Sets of the nearest POIs give a first k-th score; POIs farther than it allows are in no answer, so they get no distances.
    """
    m, a, b = len(q.tags), q.alpha / ix.w_max, (1 - q.alpha) * ix.ratio / ix.r_max
    first = ix.net.distances(g.legs.start)[ix.poi_v]
    found: dict[tuple[int, ...], tuple[int, tuple[int, ...]]] = {}

    def offer(members: tuple[int, ...], d: int, pois: tuple[int, ...], rating: int) -> None:
        g.counters["routes"] += 1
        names = g.names(pois)
        if q.route_scope != "all_orders":
            if members in found and (d, names) >= found[members]:
                return
            if old := found.get(members):  # a set's better order takes the place of its row; nothing that left the pool comes back
                pool.rows = [r for r in pool.rows if (r[1], r[2]) != old]
            found[members] = (d, names)
        pool.offer(ix.score(d, rating, q.alpha), d, rating, names)

    few = next(n for n in range(1, q.k + 1) if n**m >= q.k)
    nearest = [sorted(found_, key=lambda p: int(first[p]))[:few] for found_ in g.lists]
    g.legs.wanted = [int(ix.poi_v[p]) for found_ in nearest for p in found_]
    for members in product(*nearest):
        rating = sum(g.hits.of(j, p) for j, p in enumerate(members))
        for order in g.legs.orders:
            pois = tuple(members[j] for j in order)
            d = g.legs.route(list(pois))
            if d < FAR and d <= g.budget:
                offer(members, d, pois, rating)
    radius = min(g.budget, ix.radius(q.alpha, g.tau, pool.floor))
    limit = None if radius >= FAR else int(radius) + 1
    lists = [np.array([p for p in found_ if first[p] <= radius and first[p] < FAR], np.int64) for found_ in g.lists]
    if not all(map(len, lists)):
        return pool.answers(), g.counters
    spots, at = np.unique(ix.poi_v[np.concatenate(lists)], return_inverse=True)
    at = np.split(at, np.cumsum([len(x) for x in lists])[:-1])
    step = max(1, min(64, WORK_BYTES // (8 * len(ix.net.ids))))
    between = np.concatenate([ix.net.many(spots[i : i + step], limit)[:, spots] for i in range(0, len(spots), step)])
    ratings = [np.array([g.hits.of(j, int(p)) for p in found_], np.int64) for j, found_ in enumerate(lists)]
    home = [np.array([g.home(int(p)) for p in found_], np.int64) for found_ in lists]
    worth = lambda d: np.where(d < FAR, -a * d.astype(float), -np.inf)

    for order in g.legs.orders:
        legs = [first[lists[order[0]]]] + [between[np.ix_(at[i], at[j])] for i, j in zip(order[:-1], order[1:], strict=True)]
        ahead = [worth(home[order[-1]]) + b * ratings[order[-1]]]
        for i in range(m - 1, 0, -1):
            ahead.insert(0, b * ratings[order[i - 1]] + (worth(legs[i]) + ahead[0]).max(1))

        def grow(level: int, row: np.ndarray, d: int, rating: int, chosen: tuple[int, ...]) -> None:
            j = order[level]
            value = -a * d + b * rating + worth(row) + ahead[level]
            for x in np.argsort(-value, kind="stable").tolist():
                if value[x] == -np.inf or pool.floor is not None and value[x] < pool.floor - SLACK:
                    break
                total, rated, now = d + int(row[x]), rating + int(ratings[j][x]), (*chosen, int(lists[j][x]))
                if total > g.budget:
                    continue
                if level + 1 < m:
                    grow(level + 1, legs[level + 1][x], total, rated, now)
                elif total + int(home[j][x]) <= g.budget:
                    place = dict(zip(order, now, strict=True))
                    offer(tuple(place[i] for i in range(m)), total + int(home[j][x]), now, rated)

        grow(0, legs[0], 0, 0, ())
    return pool.answers(), g.counters


def progressive(ix: Arrays, q: QuerySpec) -> tuple[list, dict[str, int]]:
    """Partial routes grow by neighbouring hit POIs, the shortest first, until no longer one can beat the k-th score."""
    g, pool = _Legwork(ix, q), Pool(q.k)
    if not g.ok:
        return [], g.counters
    m, best_of_set = len(q.tags), {}
    heap: list[tuple[int, tuple[int, ...], int, int, int]] = [(0, (), 0, g.legs.start, 0)]  # distance, POIs, tags taken, vertex, rating
    while heap:
        d, pois, mask, at, rating = heapq.heappop(heap)
        if d > min(g.budget, ix.radius(q.alpha, g.tau, pool.floor)):
            break
        g.counters["labels"] += 1
        if mask == (1 << m) - 1:
            total, key = d, frozenset(pois) if q.route_scope == "per_set" else pois
            g.counters["routes"] += 1
            if key not in best_of_set or (total, g.names(pois)) < best_of_set[key]:
                best_of_set[key] = (total, g.names(pois))
                if q.route_scope == "per_set":
                    pool.rows = [r for r in pool.rows if frozenset(r[2]) != frozenset(g.names(pois)) or r[3] != rating]
                pool.offer(ix.score(total, rating, q.alpha), total, rating, g.names(pois))
            continue
        for j in [mask.bit_length()] if q.order else [j for j in range(m) if not mask >> j & 1]:
            for p in g.lists[j]:
                nd = d + g.leg(at, p)
                done = mask | 1 << j
                if done == (1 << m) - 1:
                    nd += g.home(p)
                if nd < FAR:
                    heapq.heappush(heap, (nd, (*pois, p), done, int(ix.poi_v[p]), rating + g.hits.of(j, p)))
    return pool.answers(), g.counters


def dominance(ix: Arrays, q: QuerySpec) -> tuple[list, dict[str, int]]:
    """Distance alone (equal ratings): of labels with the same tags taken and the same end, the k shortest stay. Every order is an answer."""
    g, pool = _Legwork(ix, q), Pool(q.k)
    if not g.ok:
        return [], g.counters
    m, kept = len(q.tags), {}
    heap = [(0, (), 0, -1, 0)]
    while heap and pool.floor is None:
        d, pois, mask, last, rating = heapq.heappop(heap)
        full = mask == (1 << m) - 1
        if not full:
            if kept.get((mask, last), 0) >= q.k:
                continue
            kept[mask, last] = kept.get((mask, last), 0) + 1
        g.counters["labels"] += 1
        if full:
            if d <= g.budget:
                pool.offer(ix.score(d, rating, q.alpha), d, rating, g.names(pois))
            continue
        at = g.legs.start if last < 0 else int(ix.poi_v[last])
        for j in [mask.bit_length()] if q.order else [j for j in range(m) if not mask >> j & 1]:
            for p in g.lists[j]:
                nd = d + g.leg(at, p) + (g.home(p) if mask | 1 << j == (1 << m) - 1 else 0)
                if nd < FAR:
                    heapq.heappush(heap, (nd, (*pois, p), mask | 1 << j, p, rating + g.hits.of(j, p)))
    return pool.answers(), g.counters


def ordered_pref(ix: Arrays, q: QuerySpec) -> tuple[list, dict[str, int]]:
    """Fixed order with ratings: tag after tag, the k best labels of each POI stay (k best by distance within the budget too)."""
    g, pool = _Legwork(ix, q), Pool(q.k)
    if not g.ok:
        return [], g.counters
    layer: dict[int, list[tuple[int, int, tuple[int, ...]]]] = {-1: [(0, 0, ())]}
    for j, found in enumerate(g.lists):
        nxt = {}
        for p in found:
            rows = []
            for last, labels in layer.items():
                leg = g.leg(g.legs.start if last < 0 else int(ix.poi_v[last]), p)
                if leg < FAR:
                    rows += [(d + leg, r + g.hits.of(j, p), (*pois, p)) for d, r, pois in labels if d + leg <= g.budget]
            g.counters["labels"] += len(rows)
            rows.sort(key=lambda x: (-ix.score(x[0], x[1], q.alpha), x[0], g.names(x[2])))
            if q.budget is None:
                nxt[p] = rows[: q.k]
            else:  # under a budget a worse but shorter label can still win: those not dominated k times
                nxt[p] = _undominated(rows, q.k)
        layer = {p: rows for p, rows in nxt.items() if rows}
    for p, rows in layer.items():
        for d, r, pois in rows:
            total = d + g.home(p)
            if total <= g.budget and total < FAR:
                pool.offer(ix.score(total, r, q.alpha), total, r, g.names(pois))
    return pool.answers(), g.counters


def _undominated(rows: list[tuple[int, int, tuple[int, ...]]], k: int) -> list[tuple[int, int, tuple[int, ...]]]:
    """Labels that fewer than k others beat in both distance and score; rows come best score first."""
    out, dists = [], []
    for row in rows:
        if sum(d <= row[0] for d in dists) < k:
            out.append(row)
        dists.append(row[0])
    return out


def ordered_astar(ix: Arrays, q: QuerySpec) -> tuple[list, dict[str, int]]:
    """Fixed order, distance alone: labels by distance so far plus the least that the remaining tags need."""
    g, pool = _Legwork(ix, q), Pool(q.k)
    if not g.ok:
        return [], g.counters
    m = len(q.tags)
    ahead: list[dict[int, int]] = [{} for _ in range(m)]
    for p in g.lists[m - 1]:
        ahead[m - 1][p] = g.home(p)
    for j in range(m - 2, -1, -1):
        for p in g.lists[j]:
            ahead[j][p] = min(g.leg(int(ix.poi_v[p]), n) + ahead[j + 1][n] for n in g.lists[j + 1])
    heap = [(g.leg(g.legs.start, p) + ahead[0][p], g.leg(g.legs.start, p), (p,), g.hits.of(0, p)) for p in g.lists[0]]
    heapq.heapify(heap)
    while heap:
        f, d, pois, rating = heapq.heappop(heap)
        if f > g.budget or f >= FAR or pool.floor is not None and ix.score(f, rating, q.alpha) < pool.floor and q.ratings == "identical":
            break
        g.counters["labels"] += 1
        j = len(pois)
        if j == m:
            pool.offer(ix.score(f, rating, q.alpha), f, rating, g.names(pois))
            continue
        for p in g.lists[j]:
            nd = d + g.leg(int(ix.poi_v[pois[-1]]), p)
            heapq.heappush(heap, (nd + ahead[j][p], nd, (*pois, p), rating + g.hits.of(j, p)))
    return pool.answers(), g.counters


def budget_labels(ix: Arrays, q: QuerySpec) -> tuple[list, dict[str, int]]:
    """The single best route within a budget: labels (tags taken, end, distance, rating), of which dominated ones go; ratings are scaled by epsilon if asked for."""
    g, pool = _Legwork(ix, q), Pool(1)
    if not g.ok:
        return [], g.counters
    m, step = len(q.tags), max(1.0, q.epsilon * g.tau / max(1, len(q.tags)))
    labels: dict[tuple[int, int], list[tuple[int, int]]] = {}
    heap = [(0, (), 0, -1, 0)]
    while heap:
        d, pois, mask, last, rating = heapq.heappop(heap)
        if d > g.budget:
            break
        scaled = int(rating // step)
        if mask != (1 << m) - 1:
            mine = labels.setdefault((mask, last), [])
            if any(a <= d and b >= scaled for a, b in mine) and (d, scaled) not in mine:
                continue
            mine.append((d, scaled))
        g.counters["labels"] += 1
        if mask == (1 << m) - 1:
            pool.offer(ix.score(d, rating, q.alpha), d, rating, g.names(pois))
            continue
        at = g.legs.start if last < 0 else int(ix.poi_v[last])
        for j in [mask.bit_length()] if q.order else [j for j in range(m) if not mask >> j & 1]:
            for p in g.lists[j]:
                nd = d + g.leg(at, p) + (g.home(p) if mask | 1 << j == (1 << m) - 1 else 0)
                if nd <= g.budget and nd < FAR:
                    heapq.heappush(heap, (nd, (*pois, p), mask | 1 << j, p, rating + g.hits.of(j, p)))
    return pool.answers(), g.counters


def _greedy(ix: Arrays, q: QuerySpec, key: Callable) -> tuple[list, dict[str, int]]:
    g, pool = _Legwork(ix, q), Pool(q.k)
    if not g.ok:
        return [], g.counters
    at, left, pois, dist, rating = g.legs.start, list(range(len(q.tags))), (), 0, 0
    while left:
        found = [(key(g.leg(at, p), g.hits.of(j, p)), j, int(ix.poi[p]), p) for j in ([left[0]] if q.order else left) for p in g.lists[j]]
        _, j, _, p = min(found)
        dist, rating, pois, at = dist + g.leg(at, p), rating + g.hits.of(j, p), (*pois, p), int(ix.poi_v[p])
        left.remove(j)
    dist += g.home(pois[-1])
    if dist < FAR and dist <= g.budget:
        pool.offer(ix.score(dist, rating, q.alpha), dist, rating, g.names(pois))
    return pool.answers(), g.counters


def greedy_nearest(ix: Arrays, q: QuerySpec) -> tuple[list, dict[str, int]]:
    """Always the nearest hit POI of a tag still open: one route, no guarantee."""
    return _greedy(ix, q, lambda d, r: (d, -r))


def greedy_rating(ix: Arrays, q: QuerySpec) -> tuple[list, dict[str, int]]:
    """Always the best rated one, the nearest of those."""
    return _greedy(ix, q, lambda d, r: (-r, d))


METHODS = {
    "ebs": explore_and_bound, "exhaustive": exhaustive, "progressive": progressive, "dominance": dominance, "ordered_pref": ordered_pref,
    "ordered_astar": ordered_astar, "budget_labels": budget_labels, "greedy_nearest": greedy_nearest, "greedy_rating": greedy_rating,
}
