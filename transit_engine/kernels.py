"""Routers as array programs: the timetable in a broadcast, blocks of requests per task, no shuffle.

These serve batches whose timetable fits an executor (its size is checked before it is collected);
the frame-based routers serve those that don't. Both give the same labels."""

from __future__ import annotations

import heapq
from collections.abc import Iterator
from functools import cached_property

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from .schema import Network

_NEVER = np.int32(2**30)
#: Events a broadcast timetable may have: 16 bytes each, so some 320 MB.
MOST_EVENTS = 20_000_000
#: Transfers that may be broadcast: 12 bytes each on the executors, more while the driver gathers them.
MOST_TRANSFERS = 20_000_000


def _packed(route: pa.Table) -> pa.Table:
    """One route's events as bytes, so that the driver gathers 4 bytes an event: stops, times by trip, trips."""
    e = route.sort_by([("rank", "ascending"), ("idx", "ascending")])
    rank, stop, arr, trip = (e[c].to_numpy() for c in ("rank", "stop_id", "arr", "trip_id"))
    size = int(np.searchsorted(rank, rank[0], side="right"))
    parts = (stop[:size].astype(np.int64), arr.astype(np.int32), trip[::size].astype(np.int64))
    return pa.table({"route_id": pa.array([e["route_id"][0].as_py()], pa.int64())} | {n: pa.array([x.tobytes()], pa.binary()) for n, x in zip(("stops", "times", "trips"), parts, strict=True)})


class Arrays:
    """A timetable as arrays: stops numbered densely; per route its stops and a (trips + 1, length)
    matrix of times whose last row stands for no trip; walks as two arrays and per stop."""

    def __init__(self, net: Network):
        n = net.events.count()
        if n > MOST_EVENTS:
            raise ValueError(f"{n} events are too many to broadcast; use round_router or segment_router")
        packed = net.events.select("route_id", "rank", "idx", "stop_id", "arr", "trip_id").groupBy("route_id").applyInArrow(_packed, "route_id long, stops binary, times binary, trips binary")
        self.ids = np.sort(net.stops.select("stop_id").toPandas()["stop_id"].to_numpy())
        self.routes, self.trips = [], []
        for route, stops, times, trips in packed.toPandas().sort_values("route_id").itertuples(index=False):
            at = np.searchsorted(self.ids, np.frombuffer(stops, np.int64)).astype(np.int32)
            t = np.vstack([np.frombuffer(times, np.int32).reshape(-1, len(at)), np.full((1, len(at)), _NEVER, np.int32)])
            self.routes.append((at, np.ascontiguousarray(t.T)))
            self.trips.append((int(route), np.frombuffer(trips, np.int64)))
        w = net.walks.toPandas()
        self.walk_a, self.walk_b = np.searchsorted(self.ids, w["a"]), np.searchsorted(self.ids, w["b"])
        self.walk_s = w["secs"].to_numpy(np.int32)

    def of(self, stop_ids: np.ndarray) -> np.ndarray:
        return np.searchsorted(self.ids, stop_ids)

    @cached_property
    def calls(self) -> list[list[tuple[int, int]]]:
        """Per stop the (route number, index) of the routes that call there."""
        out: list[list[tuple[int, int]]] = [[] for _ in self.ids]
        for r, (stops, _) in enumerate(self.routes):
            for i, s in enumerate(stops.tolist()):
                out[s].append((r, i))
        return out

    @cached_property
    def base(self) -> np.ndarray:
        """Number of the first trip of every route, trips counted through all routes, and the end."""
        return np.concatenate([[0], np.cumsum([len(ids) for _, ids in self.trips])])


def round_labels(net: Arrays, source, target, dep, k: int, prune: bool = True, admit: np.ndarray | None = None) -> np.ndarray:
    """(k + 1, requests): earliest arrival with at most n transfers, 2**30 if none; all requests of the
    block go through a route's stops together. admit: (routes, requests), whether a request may use a
    route (the cell-pruned variant)."""
    m, s = len(source), len(net.ids)
    own = np.arange(m)
    best = np.full((s, m), _NEVER, np.int32)
    best[source, own] = dep
    # walks from the sources: rows of the walk table by source
    for a, b, w in zip(net.walk_a, net.walk_b, net.walk_s, strict=True):
        at = np.flatnonzero(source == a)
        if len(at):
            best[b, at] = np.minimum(best[b, at], dep[at] + w)
    marked = best < _NEVER
    label = np.full(m, _NEVER, np.int32)
    out = np.empty((k + 1, m), np.int32)
    for n in range(k + 1):
        new = np.full((s, m), _NEVER, np.int32)
        some = marked.any(1)
        for r, (stops, times) in enumerate(net.routes):
            hot = some[stops[:-1]]
            if not hot.any() or (admit is not None and not admit[r].any()):
                continue
            none = times.shape[1] - 1
            cur = None
            for i in range(int(np.argmax(hot)), len(stops)):
                st = stops[i]
                if cur is not None:
                    np.minimum(new[st], times[i][cur], out=new[st])
                if i < len(stops) - 1 and some[st]:
                    at = np.flatnonzero(marked[st] if admit is None else marked[st] & admit[r])
                    got = np.searchsorted(times[i, :none], best[st, at], side="left")
                    if cur is None:
                        cur = np.full(m, none)
                    cur[at] = np.minimum(cur[at], got)
        walked = new.copy()
        for a, b, w in zip(net.walk_a, net.walk_b, net.walk_s, strict=True):
            np.minimum(walked[b], new[a] + w, out=walked[b])
        label = np.minimum(label, walked[target, own])
        out[n] = label
        marked = walked < best
        if prune:
            marked &= walked < label
        np.minimum(best, walked, out=best)
    return out


def event_dijkstra(net: Arrays, departures, source: int, target: int, dep: int, walks: dict) -> int:
    """Earliest arrival with any number of transfers on the time-expanded graph: nodes are departures;
    edges wait for the next departure of the stop, ride on, or walk after alighting."""
    goal = _NEVER
    heap = [(dep, source, -1, -1)]
    heap += [(dep + w, b, -1, -1) for b, w in walks.get(source, ())]
    heapq.heapify(heap)
    seen_stop: dict[int, int] = {}
    done = set()
    while heap:
        t, stop, route, spot = heapq.heappop(heap)
        if t >= goal:
            break
        if route < 0:  # arrived at a stop on foot or off a vehicle: enter its chain of departures
            if seen_stop.get(stop, _NEVER) <= t:
                continue
            seen_stop[stop] = t
            times = departures[stop][0]
            at = int(np.searchsorted(times, t))
            if at < len(times):
                heapq.heappush(heap, (int(times[at]), stop, 0, at))
            continue
        if (stop, spot) in done:
            continue
        done.add((stop, spot))
        times, rides, _ = departures[stop]
        if spot + 1 < len(times):
            heapq.heappush(heap, (int(times[spot + 1]), stop, 0, spot + 1))
        r, i, trip = rides[spot].tolist()
        stops, matrix = net.routes[r]
        there, when = int(stops[i + 1]), int(matrix[i + 1, trip])
        if there == target:
            goal = min(goal, when)
        if i + 2 < len(stops):
            nxt = departures[there][2].get((r, i + 1, trip))
            if nxt is not None:
                heapq.heappush(heap, (when, there, 0, nxt))
        for b, w in walks.get(there, ()):
            if b == target:
                goal = min(goal, when + w)
            heapq.heappush(heap, (when + w, b, -1, -1))
        heapq.heappush(heap, (when, there, -1, -1))
    return int(goal)


class Places:
    """Where the departure of (route, index, trip) stands among its stop's, as arrays by route."""

    def __init__(self, by_route: list[np.ndarray]):
        self.by_route = by_route

    def get(self, key: tuple[int, int, int]) -> int:
        r, i, trip = key
        return int(self.by_route[r][i, trip])


def departure_lists(net: Arrays):
    """Per stop: sorted departure times, their (route, index, trip), and the place of each; some 24 bytes a departure."""
    shapes = [(len(stops) - 1, times.shape[1] - 1) for stops, times in net.routes]
    flat = lambda parts: np.concatenate([np.zeros(0, np.int32), *parts]).astype(np.int32)
    stop = flat([np.repeat(stops[:-1], n) for (stops, _), (_, n) in zip(net.routes, shapes, strict=True)])
    time = flat([times[:-1, :-1].ravel() for _, times in net.routes])
    ride = np.stack([
        flat([np.full(m * n, r) for r, (m, n) in enumerate(shapes)]), flat([np.repeat(np.arange(m), n) for m, n in shapes]), flat([np.tile(np.arange(n), m) for m, n in shapes])
    ], 1)
    o = np.lexsort((ride[:, 2], ride[:, 1], ride[:, 0], time, stop))
    edge = np.searchsorted(stop[o], np.arange(len(net.ids) + 1))
    place = np.empty(len(o), np.int32)
    place[o] = np.arange(len(o)) - edge[stop[o]]
    cut = np.cumsum([m * n for m, n in shapes])[:-1]
    places = Places([p.reshape(shape) for p, shape in zip(np.split(place, cut), shapes, strict=True)] if shapes else [])
    time, ride = time[o], ride[o]
    return [(time[s:z], ride[s:z], places) for s, z in zip(edge[:-1].tolist(), edge[1:].tolist(), strict=True)]


def _grouped(time: np.ndarray, row: np.ndarray) -> tuple[np.ndarray, np.ndarray]:
    """Order by falling time, then row; where in it a new pair of both starts."""
    key = (-time.astype(np.int64) << 32) + row
    o = np.argsort(key)
    key = key[o]
    return o, np.flatnonzero(np.concatenate([[True], key[1:] != key[:-1]]))[: len(key)]


def _lowered(state: np.ndarray, rows: np.ndarray, starts: np.ndarray, source: np.ndarray, at: np.ndarray) -> np.ndarray:
    """Lowers rows of state to those of source, of which each has the ones at places from its start on; the
    rows as they are then. The first of all are taken together, then the second and so on: reduceat is slower."""
    new = np.minimum(state.take(rows, 0), source.take(at[starts], 0))
    if len(starts) < len(at):
        size = np.diff(starts, append=len(at))
        k, some = 1, np.flatnonzero(size > 1)
        while len(some) > 16:
            new[some] = np.minimum(new[some], source.take(at[starts[some] + k], 0))
            k += 1
            some = some[size[some] > k]
        for g in some.tolist():
            np.minimum(new[g], source.take(at[starts[g] + k : starts[g] + size[g]], 0).min(0), out=new[g])
    state[rows] = new
    return new


def rides_of(net: Arrays) -> tuple[np.ndarray, np.ndarray, np.ndarray, np.ndarray]:
    """(dep, arr, from, to) of every ride from a stop to the trip's next one."""
    flat = lambda parts: np.concatenate([np.zeros(0, np.int32), *parts]).astype(np.int32)
    along = [(stops, times[:, :-1]) for stops, times in net.routes]
    return (
        flat([t[:-1].ravel() for _, t in along]), flat([t[1:].ravel() for _, t in along]),
        flat([np.repeat(stops[:-1], t.shape[1]) for stops, t in along]), flat([np.repeat(stops[1:], t.shape[1]) for stops, t in along]),
    )


class EventGraph:
    """The time-expanded graph in the order of a search from all targets back through the day.

    Nodes are arrivals: a stop and a time. From a node one waits for the stop's next departures, or walks
    and waits there; a departure's ride leads to the node of its arrival. In order of falling time every
    edge's head is settled before its tail, so one pass gives the shortest paths to many targets at once:
    a row of labels per stop (of what departs from now on) and per node that a ride still needs, a column
    per target. Staying aboard is to wait no time for the trip's own next departure."""

    def __init__(self, net: Arrays):
        dep, arr, frm, to = rides_of(net)
        self.stops = s = len(net.ids)
        key, node = np.unique((-arr.astype(np.int64) << 32) + to, return_inverse=True)
        node = node.astype(np.int32)
        self.node_stop, self.node_time = (key & 0xFFFFFFFF).astype(np.int32), -(key >> 32).astype(np.int32)
        del key, to
        o, starts = _grouped(dep, frm)
        self.ride_node, self.ride_start, self.ride_row = node[o], starts.astype(np.int32), frm[o[starts]]
        dep, zero = dep[o], dep[o] >= arr[o]
        del arr, frm, node, o, starts
        # walks from the nodes: read when the day has come back to the time they end
        order = np.argsort(net.walk_a, kind="stable")
        self.walk_a, self.walk_b, self.walk_s = net.walk_a[order], net.walk_b[order], net.walk_s[order]
        first = np.searchsorted(self.walk_a, np.arange(s + 1))
        many = np.diff(first)[self.node_stop]
        at = np.repeat(np.arange(len(many), dtype=np.int32), many)
        walk = np.repeat((first[self.node_stop] - np.cumsum(many) + many).astype(np.int32), many) + np.arange(len(at), dtype=np.int32)
        end = (self.node_time[at] + self.walk_s[walk]).astype(np.int32)
        o, starts = _grouped(end, at)
        self.walk_row, self.walk_start, self.walk_node = self.walk_b[walk[o]].astype(np.int32), starts.astype(np.int32), at[o[starts]]
        end, none = end[o], self.walk_s[walk[o]] <= 0
        del at, walk, o, many
        self.codes = np.unique(np.concatenate([np.unique(self.node_time), np.unique(end)])).astype(np.int32)
        self.times = np.unique(np.concatenate([np.unique(dep), self.codes]))[::-1]
        self.level = {}
        for name, when, start in (("ride", dep, self.ride_start), ("walk", end, self.walk_start), ("node", self.node_time, None)):
            edge = np.concatenate([np.searchsorted(-when, -self.times), [len(when)]])
            self.level[name] = edge
            if start is not None:
                self.level[f"{name} group"] = np.searchsorted(start, edge)
        again = np.zeros(len(self.times), bool)
        again[np.searchsorted(-self.times, -dep[zero])] = True
        again[np.searchsorted(-self.times, -end[none])] = True
        self.again = again
        # nodes take turns in as many rows as are ever between the first that is still needed and the last that a walk has come to
        self.seen = np.searchsorted(-self.node_time, -(self.times.astype(np.int64) - int(self.walk_s.max(initial=0))), side="right")
        low = np.minimum.accumulate(np.concatenate([self.ride_node, [len(self.node_time)]])[::-1])[::-1]
        self.rows = max(1, int((self.seen - low[self.level["ride"][:-1]]).max(initial=1)), int(np.diff(self.level["node"]).max(initial=1)))
        self.ride_node %= self.rows
        self.walk_node %= self.rows
        self.kind = np.uint16 if len(self.codes) < 2**16 - 1 else np.uint32

    def lanes(self, memory: int = 48_000_000) -> int:
        """Targets of a block, by the memory of their labels."""
        return int(min(256, max(8, memory // ((self.rows + self.stops) * self.kind().itemsize))))

    def _reach(self, goal: np.ndarray, until: int):
        """Nodes from which a target is reached at once or on foot: (node, column, code of the arrival), by node."""
        into = np.concatenate([goal, self.walk_a[w := np.flatnonzero(np.isin(self.walk_b, goal))]])
        column = np.concatenate([np.arange(len(goal)), np.searchsorted(goal, self.walk_b[w])])
        secs = np.concatenate([np.zeros(len(goal), np.int64), self.walk_s[w]])
        o = np.argsort(into, kind="stable")
        first = np.searchsorted(into[o], np.arange(self.stops + 1))
        many = np.diff(first)
        node = np.flatnonzero((many > 0)[self.node_stop] & (self.node_time <= until))
        stop = self.node_stop[node]
        node = np.repeat(node, many[stop])
        at = o[np.repeat(first[stop] - np.cumsum(many[stop]) + many[stop], many[stop]) + np.arange(len(node))]
        return node, column[at], np.searchsorted(self.codes, self.node_time[node] + secs[at])

    def search(self, source: np.ndarray, target: np.ndarray, dep: np.ndarray, until: int) -> np.ndarray:
        """Earliest arrivals of requests over what has arrived until a time, 2**30 if none."""
        goal, lane = np.unique(target, return_inverse=True)
        never = np.iinfo(self.kind).max
        stop, node = np.full((self.stops, len(goal)), never, self.kind), np.full((self.rows, len(goal)), never, self.kind)
        hit, column, code = self._reach(goal, until)
        flat = (hit % self.rows) * len(goal) + column
        hit_level = np.searchsorted(hit, self.level["node"])
        first = np.searchsorted(self.walk_a, np.arange(self.stops + 1))
        many = 1 + np.diff(first)[source]
        asked = np.repeat(np.arange(len(source)), many)
        k = np.arange(len(asked)) - np.repeat(np.cumsum(many) - many, many)
        walk = np.where(k > 0, first[source][asked] + k - 1, 0)
        foot = lambda x, own: np.where(k > 0, x[walk] if len(x) else 0, own)
        start, when = foot(self.walk_b, source[asked]), dep[asked] + foot(self.walk_s, 0)
        o = np.argsort(-when, kind="stable")
        asked, start, when, cell = asked[o], start[o], when[o], lane[asked[o]]
        # what departs from a time on is there when the last level not before that time is done
        ready = np.searchsorted(-self.times, -when, side="right") - 1
        edge = np.searchsorted(ready, np.arange(len(self.times) + 1))
        out = np.full(len(source), never, self.kind)
        begin = int(np.searchsorted(-self.times, -until))
        close = int(ready.max(initial=-1)) + 1
        fresh = int(self.seen[begin - 1]) if begin else 0
        level = {name: x.tolist() for name, x in self.level.items()}
        cells, code, again, first_pass = node.reshape(-1), code.astype(self.kind), self.again.tolist(), self.again.tolist()
        for t in range(begin, close):
            if (new := int(self.seen[t])) > fresh:
                a, z = fresh % self.rows, new - fresh
                node[a : a + z] = never
                node[: max(0, a + z - self.rows)] = never
                fresh = new
            r, q = level["ride"][t : t + 2]
            w, x = level["walk"][t : t + 2]
            n, m = level["node"][t : t + 2]
            more = True
            while more:  # where rides or walks take no time, once more until nothing changes
                more = False
                if r < q:
                    g = slice(*level["ride group"][t : t + 2])
                    rows = self.ride_row[g]
                    before = stop[rows] if again[t] else None
                    made = _lowered(stop, rows, self.ride_start[g] - r, node, self.ride_node[r:q])
                    more = before is not None and (first_pass[t] or bool((made < before).any()))
                    first_pass[t] = False
                if w < x:
                    g = slice(*level["walk group"][t : t + 2])
                    _lowered(node, self.walk_node[g], self.walk_start[g] - w, stop, self.walk_row[w:x])
                if n < m:
                    a, h = n % self.rows, slice(hit_level[t], hit_level[t + 1])
                    rows = slice(a, a + m - n) if a + m - n <= self.rows else np.arange(n, m) % self.rows
                    node[rows] = np.minimum(node[rows], stop.take(self.node_stop[n:m], 0))
                    np.minimum.at(cells, flat[h], code[h])
            e = slice(edge[t], edge[t + 1])
            np.minimum.at(out, asked[e], stop[start[e], cell[e]])
        ok = out < never
        arr = np.full(len(source), _NEVER, np.int32)
        arr[ok] = self.codes[out[ok]]
        return arr

    def earliest(self, source: np.ndarray, target: np.ndarray, dep: np.ndarray) -> np.ndarray:
        """Earliest arrivals, 2**30 if none. What arrives until a time needs nothing after it, so the day
        is searched up to an hour soon after the departures first, and later for those still open."""
        out = np.full(len(source), _NEVER, np.int32)
        if not len(self.times):
            return out
        last = int(self.times[0])
        span, step = last - int(self.times[-1]), 8
        left = np.arange(len(source))
        while len(left):
            until = last if step < 1 else min(last, int(dep[left].max()) + span // step)
            arr = self.search(source[left], target[left], dep[left], until)
            done = arr <= (until if until < last else _NEVER)
            out[left[done]] = arr[done]
            left, step = left[~done], step // 2
        return out


class Sweep:
    """Earliest arrivals of a block of requests by a pass over rides in order of departure: a row of labels
    per stop, a column per request. All rides of one departure time are taken together. Whoever is aboard
    got to the ride's first stop no later than it leaves, so labels of stops tell that as well."""

    def __init__(self, stops: int, walks: tuple[np.ndarray, np.ndarray, np.ndarray], source, target, dep, piece: int = 8192):
        self.lanes, self.piece, self.goal = len(source), piece, np.full(len(source), _NEVER, np.int32)
        o = np.argsort(walks[0], kind="stable")
        self.walk_b, self.walk_s = walks[1][o], walks[2][o]
        self.first = np.searchsorted(walks[0][o], np.arange(stops + 1))
        self.best = np.full((stops, self.lanes), _NEVER, np.int32)
        self.cells, lane = self.best.reshape(-1), np.arange(self.lanes)
        np.minimum.at(self.cells, source * self.lanes + lane, dep)
        self._walk(source, lane, dep)
        # where requests end: at the target, or at a walk to it
        by_end = np.argsort(walks[1], kind="stable")
        lo, hi = (np.searchsorted(walks[1][by_end], target, side=side) for side in ("left", "right"))
        at = by_end[np.repeat(lo - np.cumsum(hi - lo) + hi - lo, hi - lo) + np.arange(int((hi - lo).sum()))]
        end, own = np.concatenate([target, walks[0][at]]), np.concatenate([lane, np.repeat(lane, hi - lo)])
        secs, o = np.concatenate([np.zeros(self.lanes, np.int64), walks[2][at]]), np.argsort(end, kind="stable")
        self.end_lane, self.end_s, self.end_first = own[o], secs[o], np.searchsorted(end[o], np.arange(stops + 1))

    @staticmethod
    def _spread(first, stop):
        """For rows at stops: (number of the row, place) for all that first has of its stop."""
        many = first[stop + 1] - first[stop]
        row = np.repeat(np.arange(len(stop)), many)
        return row, np.repeat(first[stop] - np.cumsum(many) + many, many) + np.arange(len(row))

    def _walk(self, stop, lane, when):
        row, at = self._spread(self.first, stop)
        np.minimum.at(self.cells, self.walk_b[at] * self.lanes + lane[row], (when[row] + self.walk_s[at]).astype(np.int32))

    def done(self, dep: int) -> bool:
        return bool((self.goal <= dep).all())

    def take(self, dep: int, arr: np.ndarray, frm: np.ndarray, to: np.ndarray) -> None:
        """All rides that leave at dep; where some take no time, again until they lead nowhere new."""
        again = True
        while again:
            again = False
            for lo in range(0, len(arr), self.piece):
                a, f, t = (x[lo : lo + self.piece] for x in (arr, frm, to))
                can = (self.best.take(f, 0) <= dep) & (self.goal > dep)
                row, at = self._spread(self.end_first, t)
                ok = can[row, self.end_lane[at]]
                row, at = row[ok], at[ok]
                np.minimum.at(self.goal, self.end_lane[at], (a[row] + self.end_s[at]).astype(np.int32))
                row, lane = np.nonzero(can & (a[:, None] < self.best.take(t, 0)))
                np.minimum.at(self.cells, t[row] * self.lanes + lane, a[row])
                self._walk(t[row], lane, a[row])
                again |= bool((a[row] <= dep).any())


def layered_dijkstra(net: Arrays, departures, source: int, target: int, dep: int, k: int, walks: dict) -> list[int]:
    """Earliest arrivals with at most 0..k transfers by shortest paths on k + 1 copies of the event graph.

    Layer n holds what n rides before have led to. Its nodes are stops reached, departures waited for and
    events aboard; waiting and staying aboard keep the layer, alighting leads to the next one. A node is
    settled once per layer, and not at all where a lower layer has settled it no later."""
    best = [int(_NEVER)] * (k + 1)
    stop_seen: list[dict] = [{} for _ in best]
    wait_seen: list[dict] = [{} for _ in best]
    ride_seen: list[dict] = [{} for _ in best]
    at_stop, waiting, aboard = 0, 1, 2
    heap = [(dep + w, 0, at_stop, b, 0, 0) for b, w in ((source, 0), *walks.get(source, ()))]
    heapq.heapify(heap)

    def settled(seen, layer, key, value):
        if any(seen[l].get(key, _NEVER) <= value for l in range(layer + 1)):
            return True
        seen[layer][key] = value
        return False

    while heap:
        t, layer, kind, x, y, z = heapq.heappop(heap)
        if t >= best[layer]:
            continue
        if kind == at_stop:
            if settled(stop_seen, layer, x, t):
                continue
            at = int(np.searchsorted(departures[x][0], t))
            if at < len(departures[x][0]):
                heapq.heappush(heap, (int(departures[x][0][at]), layer, waiting, x, at, 0))
        elif kind == waiting:
            times, rides, _ = departures[x]
            if settled(wait_seen, layer, (x, y), 0):
                continue
            r, i, trip = rides[y].tolist()
            heapq.heappush(heap, (t, layer, aboard, r, trip, i))
            if y + 1 < len(times):
                heapq.heappush(heap, (int(times[y + 1]), layer, waiting, x, y + 1, 0))
        else:
            if settled(ride_seen, layer, (x, y), z):
                continue
            stops, matrix = net.routes[x]
            for j in range(z + 1, len(stops)):
                there, when = int(stops[j]), int(matrix[j, y])
                if when >= best[layer]:
                    break
                for b, w in ((there, 0), *walks.get(there, ())):
                    if b == target:
                        for n in range(layer, k + 1):
                            best[n] = min(best[n], when + w)
                    if layer < k:
                        heapq.heappush(heap, (when + w, layer + 1, at_stop, b, 0, 0))
    return best


def _walks_by_stop(net: Arrays) -> dict:
    out: dict[int, list] = {}
    for a, b, w in zip(net.walk_a.tolist(), net.walk_b.tolist(), net.walk_s.tolist(), strict=True):
        out.setdefault(a, []).append((b, w))
    return out


def segment_query(net: Arrays, transfers: dict, source: int, target: int, dep: int, k: int, walks: dict, admit=None) -> list[int]:
    """One request, one task, no vector work: the trip-segment search with first-reached indices.
    transfers: (route number, trip, index) -> [(route number, trip, index)]. admit: (whether each route is
    free, per route whether each trip is in the fill-in), the cell-pruned variant."""
    hits: dict[int, list] = {}
    for s, w in ((target, 0), *((a, w) for a, ws in walks.items() for b, w in ws if b == target)):
        for r, i in net.calls[s]:
            if i:
                hits.setdefault(r, []).append((i, w))
    reached: dict[tuple, int] = {}

    def add(queue, r, trip, i):
        if admit is not None and not admit[0][r] and not admit[1][r][trip]:
            return
        stops, times = net.routes[r]
        end = reached.get((r, trip), len(stops) - 1)
        if i >= end:
            return
        queue.append((r, trip, i, end))
        for later in range(trip, times.shape[1] - 1):
            if reached.get((r, later), len(stops)) <= i:
                break
            reached[(r, later)] = i

    queue: list = []
    for s, w in ((source, 0), *walks.get(source, ())):
        for r, i in net.calls[s]:
            stops, times = net.routes[r]
            if i < len(stops) - 1:
                trip = int(np.searchsorted(times[i, :-1], dep + w))
                if trip < times.shape[1] - 1:
                    add(queue, r, trip, i)
    label, out = int(_NEVER), []
    for _ in range(k + 1):
        nxt: list = []
        for r, trip, i, end in queue:
            times = net.routes[r][1]
            for j, w in hits.get(r, ()):
                if i < j <= end:
                    label = min(label, int(times[j, trip]) + w)
        for r, trip, i, end in queue:
            if net.routes[r][1][i + 1, trip] < label:
                for j in range(i + 1, end + 1):
                    for hop in transfers.get((r, trip, j), ()):
                        add(nxt, *hop)
        out.append(label)
        queue = nxt
    return out


def profile_search(net: Arrays, hops: "Hops", source: int, targets: dict[int, int], deps: list[int], k: int, walks: dict, with_trips: bool = False):
    """All departures deps (latest first) of one source to many targets (stop -> place in the answer).

    Returns rows (place, dep, n, arr, trips) that no later departure, fewer transfers or earlier arrival
    dominates, and the number of segments scanned. What a later departure reached with as few transfers
    stays reached: per number of transfers the least index at which every trip was boarded is kept
    through all departures, and so are the labels of all targets. A segment is scanned once for all
    targets and expanded only while its next arrival beats some target's label."""
    most = len(targets)
    label = np.full((k + 1, most), _NEVER, np.int64)
    near: dict[int, list[tuple[int, int]]] = {}
    for stop, place in targets.items():
        near.setdefault(stop, []).append((place, 0))
    for a, ws in walks.items():
        for b, w in ws:
            if b in targets:
                near.setdefault(a, []).append((targets[b], w))
    length = np.array([len(stops) for stops, _ in net.routes])
    reached = np.tile(np.repeat(length - 1, np.diff(net.base)).astype(np.int32), (k + 1, 1))
    rows, scanned = [], 0
    starts = [(w, r, i) for s, w in ((source, 0), *walks.get(source, ())) for r, i in net.calls[s] if i < length[r] - 1]
    goals = {r: [(j, p, w) for j, s in enumerate(stops.tolist()) if j for p, w in near.get(s, ())] for r, (stops, _) in enumerate(net.routes)}

    def add(queue, n, r, trip, i, parent):
        at, end = net.base[r] + trip, net.base[r + 1]
        last = int(reached[n, at])
        if i < last:
            queue.append((r, trip, i, last, parent))
            np.minimum(reached[n:, at:end], i, out=reached[n:, at:end])

    for dep in deps:
        queue: list = []
        for w, r, i in starts:
            times = net.routes[r][1]
            trip = int(np.searchsorted(times[i, :-1], dep + w))
            if trip < times.shape[1] - 1:
                add(queue, 0, r, trip, i, None)
        better: dict[tuple[int, int], tuple] = {}
        for n in range(k + 1):
            scanned += len(queue)
            for seg in queue:
                r, trip, i, end, _ = seg
                times = net.routes[r][1]
                for j, p, w in goals[r]:
                    if i < j <= end:
                        arr = int(times[j, trip]) + w
                        if arr < label[n, p]:
                            label[n:, p] = np.minimum(label[n:, p], arr)
                            better[n, p] = seg
            if n == k:
                break
            bound, nxt = label[n].max(initial=0), []
            for seg in queue:
                r, trip, i, end, _ = seg
                if net.routes[r][1][i + 1, trip] < bound:
                    for j in range(i + 1, end + 1):
                        for r2, trip2, i2 in hops.get((r, trip, j)):
                            add(nxt, n + 1, r2, trip2, i2, seg)
            queue = nxt
        for (n, p), seg in sorted(better.items(), key=lambda x: x[0]):
            if n and label[n, p] >= label[n - 1, p]:
                continue
            trips = []
            while with_trips and seg is not None:
                trips.append(int(net.trips[seg[0]][1][seg[1]]))
                seg = seg[4]
            rows.append((p, dep, n, int(label[n, p]), trips))
    return rows, scanned


class Hops:
    """Transfers by (route number, trip, index), in arrays: a start per stop event, then the trips met."""

    def __init__(self, net: Arrays, transfers: DataFrame):
        n = transfers.count()
        if n > MOST_TRANSFERS:
            raise ValueError(f"{n} transfers are too many to broadcast; use segment_router")
        t = transfers.select("t1", "i1", "t2", "i2").toPandas()
        place = {int(x): (r, k) for r, (_, ids) in enumerate(net.trips) for k, x in enumerate(ids)}
        size = [len(stops) for stops, _ in net.routes]
        self.base = np.concatenate([[0], np.cumsum([len(ids) * z for (_, ids), z in zip(net.trips, size, strict=True)])])
        self.size = np.array(size)
        r1, k1 = (np.array([place[x][i] for x in t["t1"].tolist()], np.int64) for i in (0, 1))
        r2, k2 = (np.array([place[x][i] for x in t["t2"].tolist()], np.int32) for i in (0, 1))
        at = self.base[r1] + k1 * self.size[r1] + t["i1"].to_numpy()
        o = np.argsort(at, kind="stable")
        self.start = np.searchsorted(at[o], np.arange(self.base[-1] + 1))
        self.to = np.stack([r2[o], k2[o], t["i2"].to_numpy(np.int32)[o]], 1)

    def get(self, key: tuple[int, int, int], _=()) -> list[list[int]]:
        r, trip, i = key
        e = self.base[r] + trip * self.size[r] + i
        return self.to[self.start[e] : self.start[e + 1]].tolist()


def fanout_blocks(net: Network, transfers: DataFrame, groups: DataFrame, targets: DataFrame, lo: int, hi: int, k: int = 4, with_trips: bool = False) -> DataFrame:
    """(g, source, target, dep, n, arr, trips, scanned): profiles of groups (g, source) to their targets
    (g, target) over all departures in lo..hi; scanned: segments of the group's whole search. One group is
    one search inside a task, against a timetable and transfers broadcast after a check of their sizes."""
    a = Arrays(net)
    sent = groups.sparkSession.sparkContext.broadcast((a, Hops(a, transfers), _walks_by_stop(a)))
    lists = targets.groupBy("g").agg(F.sort_array(F.collect_set("target")).alias("targets"))
    work = groups.join(lists, "g").select("g", "source", "targets").repartition(max(1, groups.sparkSession.sparkContext.defaultParallelism * 4), "g")

    def run(batches: Iterator[pa.RecordBatch]):
        a, hops, walks = sent.value
        for b in batches:
            for g, source, goals in zip(*(c.to_pylist() for c in b.columns), strict=True):
                s = int(a.of(source))
                deps = set()
                for stop, w in ((s, 0), *walks.get(s, ())):
                    for r, i in a.calls[stop]:
                        stops, times = a.routes[r]
                        if i < len(stops) - 1:
                            deps.update((times[i, :-1] - w).tolist())
                deps = sorted((d for d in deps if lo <= d <= hi), reverse=True)
                at = a.of(np.array(goals))
                rows, scanned = profile_search(a, hops, s, {int(x): p for p, x in enumerate(at)}, deps, k, walks, with_trips)
                cols = list(zip(*rows, strict=True)) if rows else [[]] * 5
                n = len(rows)
                yield pa.record_batch([
                    pa.array([g] * n, pa.int64()), pa.array([source] * n, pa.int64()), pa.array([goals[p] for p in cols[0]], pa.int64()),
                    *(pa.array(c, pa.int32()) for c in cols[1:4]), pa.array(cols[4], pa.list_(pa.int64())), pa.array([scanned] * n, pa.int64()),
                ], names=["g", "source", "target", "dep", "n", "arr", "trips", "scanned"])

    return work.mapInArrow(run, "g long, source long, target long, dep int, n int, arr int, trips array<long>, scanned long")


class Admission:
    """Cells and fill-in in arrays: which routes and trips a request between two cells may use."""

    def __init__(self, net: Arrays, routes: DataFrame, fillin: DataFrame):
        """routes: (route_id, cell); fillin: (route_id, rank), one row per trip."""
        number = {rid: r for r, (rid, _) in enumerate(net.trips)}
        self.cell = np.zeros(len(net.routes), np.int64)
        for rid, c in routes.select("route_id", "cell").toPandas().itertuples(index=False):
            if rid in number:
                self.cell[number[rid]] = c
        self.trips = [np.zeros(len(ids), bool) for _, ids in net.trips]
        for rid, rank in fillin.select("route_id", "rank").distinct().toPandas().itertuples(index=False):
            self.trips[number[rid]][rank] = True
        self.fill = np.array([t.any() for t in self.trips])

    def routes(self, source_cell: np.ndarray, target_cell: np.ndarray) -> np.ndarray:
        """(routes, requests): in one of the request's cells (0: none)."""
        c = self.cell[:, None]
        return ((c == source_cell) | (c == target_cell)) & (c > 0)


_ASK = ["req_id", "source", "target"]


def _asked(requests: DataFrame, cells: bool) -> DataFrame:
    """Requests as the blocks take them; with cells also src_cell and tgt_cell, 0 for none."""
    extra = [F.coalesce(c, F.lit(0)).cast("int").alias(c) for c in ("src_cell", "tgt_cell")] if cells else []
    return requests.select(*_ASK, F.col("dep").cast("int").alias("dep"), *extra)


def segment_blocks(net: Network, transfers: DataFrame, requests: DataFrame, k: int = 4, arrays: Arrays | None = None, hops: "Hops | None" = None, cells: Admission | None = None) -> DataFrame:
    """(req_id, n, arr), improvements only: the trip-segment search request by request inside tasks,
    against a timetable and transfers that are broadcast after a check of their sizes. cells: requests
    carry src_cell and tgt_cell and use only what these admit."""
    a = arrays or Arrays(net)
    sent = requests.sparkSession.sparkContext.broadcast((a, hops or Hops(a, transfers), _walks_by_stop(a), cells))

    def run(batches: Iterator[pa.RecordBatch]):
        a, hops, walks, cells = sent.value
        for b in batches:
            rid, s, t, d, *own = (np.asarray(c) for c in b.columns)
            free = cells.routes(*own).T if cells else [None] * len(rid)
            out = [segment_query(a, hops, int(x), int(y), int(z), k, walks, None if f is None else (f, cells.trips)) for x, y, z, f in zip(a.of(s), a.of(t), d, free, strict=True)]
            out = np.array(out, np.int32).reshape(len(rid), k + 1).T
            first = np.vstack([np.full((1, len(rid)), _NEVER, np.int32), out[:-1]])
            n, at = np.nonzero(out < first)
            yield pa.record_batch([pa.array(rid[at]), pa.array(n.astype(np.int32)), pa.array(out[n, at])], names=["req_id", "n", "arr"])

    return _asked(requests, cells is not None).mapInArrow(run, "req_id long, n int, arr int")


def route_blocks(net: Network, requests: DataFrame, k: int = 4, block: int = 1024, arrays: Arrays | None = None, cells: Admission | None = None) -> DataFrame:
    """(req_id, n, arr), improvements only, for requests of any number: tasks take blocks against the
    broadcast timetable; memory is stops times block. cells: as in segment_blocks, by whole routes."""
    a = arrays or Arrays(net)
    sent = requests.sparkSession.sparkContext.broadcast((a, cells))

    def run(batches: Iterator[pa.RecordBatch]):
        a, cells = sent.value
        for whole in batches:
            for lo in range(0, whole.num_rows, block):
                b = whole.slice(lo, block)
                rid, s, t, d, *own = (np.asarray(c) for c in b.columns)
                admit = cells.routes(*own) | cells.fill[:, None] if cells else None
                out = round_labels(a, a.of(s), a.of(t), d.astype(np.int32), k, admit=admit)
                first = np.vstack([np.full((1, len(rid)), _NEVER, np.int32), out[:-1]])
                n, at = np.nonzero(out < first)
                yield pa.record_batch([pa.array(rid[at]), pa.array(n.astype(np.int32)), pa.array(out[n, at])], names=["req_id", "n", "arr"])

    return _asked(requests, cells is not None).mapInArrow(run, "req_id long, n int, arr int")
