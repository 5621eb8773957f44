"""The methods in memory, on arrays: what kernels run inside a task, and where inspections are counted exactly."""

from __future__ import annotations

import math
from collections import deque
from collections.abc import Iterable, Iterator
from dataclasses import dataclass, field, replace
from functools import cached_property
from itertools import chain

import numpy as np

BITS = 1 << 25  # visited (start, vertex) pairs that one block of searches marks
CUT = 1 << 20  # rows that searches give at once, but for a start that has more
LIST_ROWS = 64_000_000  # entries of all lists together; caps are lowered to keep to it, which changes no answer
GIANT = 1024  # vertices from which on a strongly connected part is searched once for all starts that lead into it
TRIED = 8  # vertices from which such a part is looked for
PIECE = 1 << 22  # entries that lists are united from at once
SMALL = 4096  # vertices up to which lists are Python sets: rounds over arrays cost more there
Pairs = tuple[np.ndarray, np.ndarray]


@dataclass
class Counters:
    inspect_reach: int = 0
    inspect_trail: int = 0
    inspect_search: int = 0
    reach_rows: int = 0
    n_light: int = 0
    n_heavy: int = 0
    heavy_sources: int = 0
    trail_rows: int = 0
    light_rows: int = 0
    heavy_rows: int = 0
    cap: int = 0
    out: int = 0

    def row(self) -> dict[str, int]:
        return dict(vars(self))


class Adjacency:
    """Targets of each vertex, in one array with an offset per vertex."""

    def __init__(self, src: np.ndarray, dst: np.ndarray, n: int):
        order = np.argsort(src, kind="stable")
        self.to = dst[order]
        self.at = np.zeros(n + 1, np.int64)
        np.cumsum(np.bincount(src, minlength=n), out=self.at[1:])

    def of(self, v: int) -> np.ndarray:
        return self.to[self.at[v] : self.at[v + 1]]

    def spread(self, row: np.ndarray, v: np.ndarray) -> Pairs:
        """(row, target) of every edge that leaves v, for pairs (row, v)."""
        n = self.at[v + 1] - self.at[v]
        spots = np.repeat(self.at[v] - np.concatenate(([0], np.cumsum(n)[:-1])), n) + np.arange(n.sum()) if len(v) else v
        return np.repeat(row, n), self.to[spots]


class Seen:
    """Distinct keys, kept sorted in a few arrays of falling length."""

    def __init__(self) -> None:
        self.held: list[np.ndarray] = []

    def add(self, key: np.ndarray) -> None:
        """``key`` is sorted, and none of it is here."""
        self.held.append(key)
        while len(self.held) > 1 and 2 * len(self.held[-1]) > len(self.held[-2]):
            b, a = self.held.pop(), self.held.pop()
            self.held.append(np.sort(np.concatenate((a, b)), kind="stable"))

    def fresh(self, key: np.ndarray) -> np.ndarray:
        """The keys that are not here, once each, sorted."""
        key = np.unique(key)
        for old in self.held:
            if len(old):
                key = key[old[np.minimum(np.searchsorted(old, key), len(old) - 1)] != key]
        return key

    def all(self) -> np.ndarray:
        return np.sort(np.concatenate(self.held), kind="stable") if self.held else np.zeros(0, np.int64)


@dataclass
class Shared:
    """Lists of which vertices have one in common: ``which`` names the list of each vertex, ``begin`` and ``size`` its place in ``held``."""

    which: np.ndarray
    begin: np.ndarray
    size: np.ndarray
    held: np.ndarray


@dataclass
class Local:
    """A canonical graph with dense ids: starts (s, x), middle (src, dst), ends (x, y); ``own`` and ``ys`` name s and y."""

    own: np.ndarray
    s: np.ndarray
    x: np.ndarray
    middle: Adjacency
    ends: Adjacency
    ys: np.ndarray
    n: int
    n_edges: int
    ids: np.ndarray
    counters: Counters = field(default_factory=Counters)
    new_rows: list[int] = field(default_factory=list)  # per round of all searches or of the lists: pairs found, edges looked at
    looks: list[int] = field(default_factory=list)

    @classmethod
    def build(cls, starts: Pairs, middle: Pairs, ends: Pairs) -> Local:
        ids = np.unique(np.concatenate((starts[1], *middle, ends[0])))
        dense = lambda a: np.searchsorted(ids, a)
        src, dst, n = dense(middle[0]), dense(middle[1]), len(ids)
        own, s = np.unique(starts[0], return_inverse=True)
        ys, y = np.unique(ends[1], return_inverse=True)
        order = np.argsort(s, kind="stable")
        return cls(own, s[order], dense(starts[1])[order], Adjacency(src, dst, n), Adjacency(dense(ends[0]), y, n), ys, n, len(s) + len(src) + len(y), ids)

    @cached_property
    def turned(self) -> Adjacency:
        return Adjacency(self.middle.to, np.repeat(np.arange(self.n), np.diff(self.middle.at)), self.n)

    def _round(self, i: int, new: int, looks: int) -> None:
        while len(self.new_rows) <= i:
            self.new_rows.append(0)
            self.looks.append(0)
        self.new_rows[i] += new
        self.looks[i] += looks

    def lists(self, cap: int | None, most: int | None = None) -> Adjacency | None:
        """Capped lists by rounds over arrays: the ends y of each vertex, sorted; None where they exceed ``most`` entries.

        A round offers each new entry to the vertices one middle edge before. Entries are kept as sorted keys (x, y) in a
        few arrays of falling length.
        """
        wide = max(1, len(self.ys))
        room = np.full(self.n, np.iinfo(np.int64).max if cap is None else cap, np.int64)

        def admitted(key: np.ndarray) -> np.ndarray:
            x = key // wide
            first = np.concatenate(([True], x[1:] != x[:-1])) if len(x) else np.zeros(0, bool)
            begin = np.flatnonzero(first)
            place = np.arange(len(x)) - np.repeat(begin, np.diff(np.append(begin, len(x))))
            key = key[place < room[x]]
            np.subtract.at(room, key // wide, 1)
            return key

        at = np.repeat(np.arange(self.n), np.diff(self.ends.at))
        newest, held, total, i = admitted(np.unique(at * wide + self.ends.to)), [], 0, 0
        while len(newest):
            total += len(newest)
            if most is not None and total > most:
                return None
            held.append(newest)
            while len(held) > 1 and 2 * len(held[-1]) > len(held[-2]):
                b, a = held.pop(), held.pop()
                held.append(np.sort(np.concatenate((a, b)), kind="stable"))
            x = newest // wide
            y, w = self.turned.spread(newest - x * wide, x)
            self.counters.inspect_reach += len(w)
            looked, key = len(w), np.unique((w * wide + y)[room[w] > 0])
            for old in held:
                spot = np.minimum(np.searchsorted(old, key), len(old) - 1)
                key = key[old[spot] != key]
            newest = admitted(key)
            self._round(i, len(newest), looked)
            i += 1
        key = np.sort(np.concatenate(held), kind="stable") if held else np.zeros(0, np.int64)
        return Adjacency(key // wide, key % wide, self.n)

    def _peel(self, alive: np.ndarray) -> None:
        """Strike out of ``alive`` what no cycle leads to, or what leads to none."""
        for step, back in ((self.middle, self.turned), (self.turned, self.middle)):
            row = np.repeat(np.arange(self.n), np.diff(step.at))
            left = np.bincount(row[alive[row] & alive[step.to]], minlength=self.n)
            newest = np.flatnonzero(alive & (left == 0))
            while len(newest):
                alive[newest] = False
                before = back.spread(newest, newest)[1]
                before = before[alive[before]]
                np.subtract.at(left, before, 1)
                newest = np.unique(before[left[before] == 0])

    @cached_property
    def parts(self) -> np.ndarray:
        """The strongly connected part of each vertex, as dense numbers. What lies on no cycle is struck out over arrays, and a large
        part is found from one of its vertices; the others are searched depth first."""
        part, alive, n = np.full(self.n, -1, np.int64), np.ones(self.n, bool), 0
        self._peel(alive)
        if alive.sum() > SMALL:
            ways = np.minimum(np.diff(self.middle.at), np.diff(self.turned.at))
            v = int(np.argmax(np.where(alive, ways, -1)))
            part[self._reached(self.middle, v) & self._reached(self.turned, v)] = 0
            alive &= part < 0
            n = 1
            self._peel(alive)
        core = np.flatnonzero(alive)
        place = np.full(self.n, -1, np.int64)
        place[core] = np.arange(len(core))
        row, to = self.middle.spread(np.arange(len(core)), core)
        inner = place[to] >= 0
        step = Adjacency(row[inner], place[to[inner]], len(core))
        at, to = step.at.tolist(), step.to.tolist()
        spot, met, low, own, open_, seen = at[:-1], [0] * len(core), [0] * len(core), [-1] * len(core), [], 0
        for root in range(len(core)):
            way = [] if met[root] else [root]
            while way:
                v = way[-1]
                if not met[v]:
                    seen += 1
                    met[v] = low[v] = seen
                    open_.append(v)
                while spot[v] < at[v + 1]:
                    w = to[spot[v]]
                    spot[v] += 1
                    if not met[w]:
                        way.append(w)
                        break
                    if own[w] < 0:
                        low[v] = min(low[v], met[w])
                else:
                    way.pop()
                    if way:
                        low[way[-1]] = min(low[way[-1]], low[v])
                    while low[v] == met[v] and own[v] < 0:
                        own[open_.pop()] = n
                    n += own[v] == n
        part[core] = own
        rest = np.flatnonzero(part < 0)
        part[rest] = n + np.arange(len(rest))
        return part

    def shared(self, cap: int | None, most: int | None = None) -> Shared | None:
        """The lists that ``lists`` gives, built once for vertices that have the same; None where these exceed ``most`` entries.

        Vertices of a strongly connected part have one list, and parts come after those that they lead to. A part with a full
        list ahead of it takes over that list, as it fills it; a part with one list ahead and no ends of its own does so too. Looks
        and rounds are told as of lists built apart: an entry of a vertex is offered to all vertices one middle edge before.
        """
        live = self._reached(self.turned, np.unique(np.repeat(np.arange(self.n), np.diff(self.ends.at))))
        if not live.all():  # only what leads to an end has a list
            src, kept = np.repeat(np.arange(self.n), np.diff(self.middle.at)), live[self.middle.to]
            if not live.any():
                return Shared(np.arange(self.n), *np.zeros((2, self.n), np.int64), np.zeros(0, np.int64))
            if not kept.all():
                return replace(self, middle=Adjacency(src[kept], self.middle.to[kept], self.n)).shared(cap, most)
        part, wide, cap = self.parts, max(1, len(self.ys)), np.iinfo(np.int64).max if cap is None else cap
        n = int(part.max()) + 1 if self.n else 0
        every = np.arange(self.n)
        src, dst = part[np.repeat(every, np.diff(self.middle.at))], part[self.middle.to]
        key = np.unique((src * n + dst)[src != dst])
        ahead, before = Adjacency(key // max(1, n), key % max(1, n), n), Adjacency(key % max(1, n), key // max(1, n), n)
        key = np.unique(part[np.repeat(every, np.diff(self.ends.at))] * wide + self.ends.to)
        ends = Adjacency(key // wide, key % wide, n)
        members, offers = np.bincount(part, minlength=n), np.bincount(part, np.diff(self.turned.at), n).astype(np.int64)
        begin, size, held, used, i = np.zeros(n, np.int64), np.zeros(n, np.int64), np.empty(1024, np.int64), 0, 0
        left = np.diff(ahead.at)
        ready = np.flatnonzero(left == 0)
        while len(ready):
            row, to = ahead.spread(np.arange(len(ready)), ready)
            row, to = row[size[to] > 0], to[size[to] > 0]
            same = (np.bincount(row, minlength=len(ready)) == 1) & (np.diff(ends.at)[ready] == 0)
            same[row[size[to] >= cap]] = True
            taken = same[row] & ((size[to] >= cap) | (np.bincount(row, minlength=len(ready))[row] == 1))
            begin[ready[row[taken]]], size[ready[row[taken]]] = begin[to[taken]], size[to[taken]]
            for a, to_ in self._pieces(ready[~same], row, to, same, size):
                key = ends.spread(np.arange(len(a)), a)
                key = np.unique(key[0] * wide + key[1])
                for r, t in to_:
                    count = size[t]
                    spots = np.repeat(begin[t] - (np.cumsum(count) - count), count) + np.arange(count.sum())
                    key = np.unique(np.concatenate((key, np.repeat(r, count) * wide + held[spots])))
                    r = key // wide
                    first = np.searchsorted(r, np.arange(len(a)))
                    key = key[np.arange(len(key)) - first[r] < cap]
                r = key // wide
                key = key[np.arange(len(key)) - np.searchsorted(r, np.arange(len(a)))[r] < cap]
                if most is not None and used + len(key) > most:
                    return None
                while used + len(key) > len(held):
                    held = np.concatenate((held, np.empty(len(held), np.int64)))
                held[used : used + len(key)] = key % wide
                size[a] = np.bincount(key // wide, minlength=len(a))
                begin[a] = used + np.cumsum(size[a]) - size[a]
                used += len(key)
            looks = int((size[ready] * offers[ready]).sum())
            self.counters.inspect_reach += looks
            self._round(i, int((size[ready] * members[ready]).sum()), looks)
            i += 1
            behind = before.spread(ready, ready)[1]
            np.subtract.at(left, behind, 1)
            ready = np.unique(behind[left[behind] == 0])
        return Shared(part, begin, size, held[:used])

    @staticmethod
    def _pieces(ready: np.ndarray, row: np.ndarray, to: np.ndarray, same: np.ndarray, size: np.ndarray) -> Iterator[tuple[np.ndarray, list[Pairs]]]:
        """(some parts of ``ready``, what they are united from as (place among these, part ahead)), a bounded number of entries at a time."""
        place = np.cumsum(~same) - 1  # among those that get a list of their own
        row, to = place[row[~same[row]]], to[~same[row]]
        total = np.concatenate(([0], np.cumsum(size[to])))
        at = np.searchsorted(row, np.arange(len(ready) + 1))
        lo = 0
        while lo < len(ready):
            hi = max(lo + 1, int(np.searchsorted(total[at], total[at[lo]] + PIECE, "right")) - 1)
            hi = min(hi, len(ready), lo + PIECE)
            cuts = [int(at[lo])]
            while cuts[-1] < at[hi]:
                cuts.append(min(int(at[hi]), max(cuts[-1] + 1, int(np.searchsorted(total, total[cuts[-1]] + PIECE, "right")) - 1)))
            yield ready[lo:hi], [(row[a:b] - lo, to[a:b]) for a, b in zip(cuts[:-1], cuts[1:], strict=True)]
            lo = hi

    def reach(self, cap: int | None) -> list[set[int] | None]:
        """Capped lists. Every entry that a list gains is offered once to each vertex one middle edge before."""
        lists: list[set[int] | None] = [None] * self.n
        todo: deque[tuple[int, int]] = deque()

        def add(x: int, y: int) -> None:
            own = lists[x]
            if own is None:
                own = lists[x] = set()
            if (cap is None or len(own) < cap) and y not in own:
                own.add(y)
                todo.append((x, y))

        for x in np.flatnonzero(np.diff(self.ends.at)).tolist():
            for y in sorted(self.ends.of(x).tolist()):
                add(x, y)
        while todo:
            x, y = todo.popleft()
            before = self.turned.of(x)
            self.counters.inspect_reach += len(before)
            for w in before.tolist():
                add(w, y)
        return lists

    def visits(self, only: np.ndarray | None = None) -> Iterator[Pairs]:
        """(place of s in ``own``, vertex) that searches from all starts (or those at places ``only``) visit, whole starts at a time.

        A block of sources marks what it visits in one array, of which only the marks made are read and wiped again. A
        visited pair looks at the vertex's edges once, which is what the counters say.
        """
        s, x = (self.s, self.x) if only is None else (self.s[only], self.x[only])
        who, row = np.unique(s, return_inverse=True)
        width = max(1, min(len(who), BITS // max(1, self.n)))
        seen = np.zeros(width * self.n, bool)
        for lo in range(0, len(who), width):
            a, b = np.searchsorted(row, (lo, lo + width))  # starts are sorted by s
            newest = np.unique((row[a:b] - lo) * self.n + x[a:b])
            seen[newest] = True
            walked, i = [newest], 0
            while len(newest):
                r = newest // self.n
                r, v = self.middle.spread(r, newest - r * self.n)
                self.counters.inspect_search += len(r)
                key = r * self.n + v
                newest = np.unique(key[~seen[key]])
                seen[newest] = True
                walked.append(newest)
                self._round(i, len(newest), len(r))
                i += 1
            spots = np.flatnonzero(seen) if sum(map(len, walked)) > len(seen) // 8 else np.sort(np.concatenate(walked))
            seen[spots] = False
            self.counters.trail_rows += len(spots)
            r = spots // self.n
            at = 0
            while at < len(spots):
                to = len(spots) if at + CUT >= len(spots) else max(int(np.searchsorted(r, r[at + CUT])), int(np.searchsorted(r, r[at], "right")))
                yield who[lo + r[at:to]], spots[at:to] - r[at:to] * self.n
                at = to

    def _reached(self, step: Adjacency, v: int | np.ndarray) -> np.ndarray:
        """Marks of the vertices that v (one or many) leads to, itself included."""
        seen, newest = np.zeros(self.n, bool), np.atleast_1d(v)
        while len(newest):
            seen[newest] = True
            ahead = step.spread(newest, newest)[1]
            newest = np.unique(ahead[~seen[ahead]])
        return seen

    def giant(self) -> Pairs | None:
        """Marks of the vertices that lead into a giant strongly connected part, and of those that it leads to. A search that
        meets one of the first visits all of the second. None where either are few. Some vertices are tried, and then one of the largest part."""
        if self.n < GIANT or not len(self.middle.to):
            return None
        ways = np.minimum(np.diff(self.middle.at), np.diff(self.turned.at))
        likely = np.flatnonzero(ways >= min(2, ways.max()))
        tried = likely[np.linspace(0, len(likely) - 1, min(TRIED, len(likely))).astype(np.int64)].tolist()
        for v in chain(tried, self._largest()):
            ahead = self._reached(self.middle, v)
            if ahead.sum() >= GIANT and (into := self._reached(self.turned, v)).sum() >= GIANT:
                return into, ahead
        return None

    def _largest(self) -> Iterator[int]:
        """A vertex of the largest part, found when it is asked for."""
        yield int(np.argmax(self.parts == np.argmax(np.bincount(self.parts))))

    def search(self, only: np.ndarray | None = None, crossed: list[Pairs] | None = None) -> Iterator[Pairs]:
        """(s, y) by searches from all starts (or those at places ``only``), a block of sources at a time.

        What a giant part leads to is searched once. Sources that lead into it have all its ends: such (sources, ends), of
        which all pairs are answers, go to ``crossed``, if given, instead of their pairs.
        """
        if not len(self.ends.to) and only is None and self._straight():
            return
        big = self.giant()
        s, x = (self.s, self.x) if only is None else (self.s[only], self.x[only])
        if big is None or not big[0][x].any():
            yield from self._searched(only)
            return
        into, ahead = big
        begins = np.zeros(len(self.own), bool)
        begins[s[into[x]]] = True
        hot, met = np.flatnonzero(begins), np.flatnonzero(ahead)
        y = np.unique(self.ends.spread(met, met)[1])
        degree = np.diff(self.middle.at)
        self.counters.inspect_search += len(hot) * int(degree[met].sum())
        self.counters.trail_rows += len(hot) * len(met)
        self.counters.out += len(hot) * len(y)
        if crossed is not None:
            crossed.append((self.own[hot], self.ys[y]))
        else:
            width = max(1, CUT // max(1, len(y)))
            for at in range(0, len(hot) if len(y) else 0, width):
                part = hot[at : at + width]
                yield self.own[np.repeat(part, len(y))], self.ys[np.tile(y, len(part))]
        # what these sources visit besides: no way leads back out of what the giant part leads to
        told = np.zeros(len(self.ys), bool)
        told[y] = True
        src, at = np.repeat(np.arange(self.n), degree), np.repeat(np.arange(self.n), np.diff(self.ends.at))
        apart, untold = ~ahead[self.middle.to], ~told[self.ends.to]
        beside = begins[s] & ~ahead[x]
        rest = replace(self, s=s[beside], x=x[beside], middle=Adjacency(src[apart], self.middle.to[apart], self.n), ends=Adjacency(at[untold], self.ends.to[untold], self.n))
        yield from rest._searched(None, degree - np.diff(rest.middle.at))
        cold = ~begins[s]
        yield from replace(self, s=s[cold], x=x[cold])._searched()

    def _searched(self, only: np.ndarray | None = None, unseen: np.ndarray | None = None) -> Iterator[Pairs]:
        """(s, y) by a search from every start. ``unseen``: edges per vertex that are looked at but left out of the graph."""
        wide, plain = max(1, len(self.ys)), np.bincount(self.ends.to, minlength=1).max() <= 1  # plain: no end is met at two vertices
        for s, v in self.visits(only):
            if unseen is not None:
                self.counters.inspect_search += int(unseen[v].sum())
            s, y = self.ends.spread(s, v)
            if not plain:
                key = np.unique(s * wide + y)
                s, y = key // wide, key % wide
            self.counters.out += len(s)
            yield self.own[s], self.ys[y]

    def hops(self) -> Iterator[tuple[np.ndarray, np.ndarray, np.ndarray]]:
        """(s, y, middle edges on a shortest way from s to y), a block of sources at a time, as wide as their visits allow."""
        who, at = np.unique(self.s, return_index=True)  # starts are sorted by s
        at, lo, width = np.append(at, len(self.s)), 0, max(1, min(len(who), BITS // max(1, self.n)))
        while lo < len(who):
            hi = min(len(who), lo + width)
            found = self._hops(who[lo], slice(at[lo], at[hi]), 8 * CUT if hi - lo > 1 else None)
            if found is None:
                width = max(1, width // 4)
                continue
            (s, y, far), visited = found
            yield self.own[s], self.ys[y], far
            lo, width = hi, width * 2 if visited < CUT else width

    def _hops(self, first: int, part: slice, most: int | None) -> tuple[tuple[np.ndarray, np.ndarray, np.ndarray], int] | None:
        """(s, y, hops) of a slice of the starts, and how many pairs they visit; None where these exceed ``most``."""
        wide, seen, keys, hops, visited = max(1, len(self.ys)), Seen(), [], [], 0
        newest = np.unique((self.s[part] - first) * self.n + self.x[part])
        while len(newest):
            visited += len(newest)
            if most is not None and visited > most:
                return None
            seen.add(newest)
            r = newest // self.n
            v = newest - r * self.n
            s, y = self.ends.spread(r, v)
            keys.append(s * wide + y)
            hops.append(np.full(len(s), len(hops), np.int64))
            r, v = self.middle.spread(r, v)
            newest = seen.fresh(r * self.n + v)
        key, nearest = np.unique(np.concatenate(keys), return_index=True)  # of equal keys the first
        return (key // wide + first, key % wide, np.concatenate(hops)[nearest]), visited

    def _straight(self) -> bool:
        """Without ends, where no vertex has two edges and no source two starts, a search only goes to the end of its way: the
        looks of all are the lengths of their ways, by doubling. False, with nothing counted, elsewhere and on a cycle."""
        out = np.diff(self.middle.at)
        if len(out) and out.max() > 1 or len(np.unique(self.s)) < len(self.s):
            return False
        ahead, far = np.full(self.n + 1, self.n, np.int64), np.zeros(self.n + 1, np.int64)
        ahead[:-1][out > 0], far[:-1] = self.middle.to, out
        for _ in range(self.n.bit_length()):
            far, ahead = far + far[ahead], ahead[ahead]
        if (ahead < self.n).any():
            return False
        self.counters.inspect_search += int(far[self.x].sum())
        self.counters.trail_rows += int(far[self.x].sum()) + len(self.x)
        return True

    def two_ended(self, most: int | None = None) -> Iterator[Pairs | None]:
        """(s, y) by searches from starts and ends at once; the side with fewer new pairs goes on, the first that ends knows all.
        None, and nothing else, where the two visit more than ``most`` pairs."""
        begins = Adjacency(self.x, self.s, self.n)
        sides, visited, i = [], 0, 0
        for step, at in ((self.middle, begins), (self.turned, self.ends)):
            row, v = at.spread(np.arange(self.n), np.arange(self.n))[::-1]
            newest, seen = np.unique(row * self.n + v), Seen()
            seen.add(newest)
            visited += len(newest)
            sides.append([step, newest, seen])
        while len(sides[0][1]) and len(sides[1][1]):
            side = sides[0] if len(sides[0][1]) <= len(sides[1][1]) else sides[1]
            step, newest, seen = side
            r, v = step.spread(newest // self.n, newest % self.n)
            self.counters.inspect_search += len(r)
            side[1] = seen.fresh(r * self.n + v)
            seen.add(side[1])
            visited += len(side[1])
            if most is not None and visited > most:
                yield None
                return
            self._round(i, len(side[1]), len(r))
            i += 1
        ahead = not len(sides[0][1])
        spots = (sides[0] if ahead else sides[1])[2].all()
        r, other = (self.ends if ahead else begins).spread(spots // self.n, spots % self.n)
        pairs = np.unique(np.stack((r, other) if ahead else (other, r), axis=1), axis=0)
        yield self.own[pairs[:, 0]], self.ys[pairs[:, 1]]

    def capped_split(self, cap: int | str | None = "sqrt") -> Iterator[Pairs]:
        """(s, y) by capped lists, light answers and searches from heavy starts; a pair may come from both."""
        size = math.isqrt(self.n_edges) + 1 if cap == "sqrt" else 1 if cap == "adaptive" else cap
        c = self.counters
        while True:
            if self.n <= SMALL:
                size = None if size is None else max(1, min(size, LIST_ROWS // max(1, self.n)))
                own = self.reach(size)
                at = np.repeat(np.arange(self.n), [len(x or ()) for x in own])
                lists = Adjacency(at, np.fromiter((y for x in own for y in x or ()), np.int64, len(at)), self.n)
            else:
                lists = self.lists(size, LIST_ROWS)
                while lists is None:
                    size = max(1, LIST_ROWS // self.n) if size is None else max(1, size // 4)
                    lists = self.lists(size, max(LIST_ROWS, self.n))
            long = np.diff(lists.at)
            heavy = long >= size if size is not None else np.zeros(self.n, bool)
            begins = heavy[self.x] if len(self.x) else np.zeros(0, bool)
            sources = len(np.unique(self.s[begins]))
            if cap != "adaptive" or sources <= size or size >= LIST_ROWS // max(1, self.n):
                break
            size *= 4
        c.cap, c.reach_rows, c.n_heavy, c.heavy_sources = size or 0, len(lists.to), int(heavy.sum()), sources
        c.n_light = int((long > 0).sum()) - c.n_heavy
        s, x, wide = self.s[~begins], self.x[~begins], max(1, len(self.ys))
        rows, at = np.concatenate(([0], np.cumsum(long[x]))), 0
        while at < len(s):
            to = len(s) if rows[at] + CUT >= rows[-1] else int(np.searchsorted(rows, rows[at] + CUT))
            to = len(s) if to >= len(s) else max(int(np.searchsorted(s, s[to])), int(np.searchsorted(s, s[at], "right")))  # starts are sorted by s
            row, y = lists.spread(s[at:to], x[at:to])
            key = np.unique(row * wide + y)
            c.light_rows += len(key)
            yield self.own[key // wide], self.ys[key % wide]
            at = to
        if sources:
            before, c.inspect_search = c.inspect_search, 0
            for block in self.search(np.flatnonzero(begins)):
                c.heavy_rows += len(block[0])
                yield block
            c.inspect_trail, c.inspect_search = c.inspect_search, before


def flat(found: Iterable[Pairs]) -> Pairs:
    blocks = list(found)
    none = np.empty(0, np.int64)
    return (np.concatenate([b[0] for b in blocks]), np.concatenate([b[1] for b in blocks])) if blocks else (none, none)
