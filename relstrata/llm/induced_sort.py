"""Suffix order with common prefixes by external, recursive induced sorting.

The shard is a byte string with a sentinel. Suffixes that begin a descent-then-ascent
(the seeds, about a third) are named by their substrings in sorted runs that are merged from
disk; unless all names differ, the string of names is sorted by the same code. From the
seeds' order one scan induces the suffixes larger than their successor, a second one the
rest. Both scans pop tuples (symbol, arrival, place, common prefix) from a priority queue of
symbol ranges: the current range is held sorted, later ones are queues that go to disk beyond
a memory limit. A batch is popped as far as nothing that it induces comes before its end.
A string of at most SMALL names ends the recursion: it is sorted in memory by doubling.

Common prefixes travel with the tuples: one that is pushed shares with the last of its symbol
that symbol and the least common prefix popped in between. Only where two neighbours begin with
different symbols, or one of them was known before the scan, are their bytes compared.

Everything is cut off at ``depth`` bytes for prefixes only; the order itself is exact.
Arrays as long as the shard lie in memory up to a limit, and in temporary files of the
task beyond it.
"""

from __future__ import annotations

import tempfile
from collections.abc import Callable, Iterator
from dataclasses import dataclass

import numpy as np

DEPTH = 64
PAD = 255  # never occurs in UTF-8 moved up by two; above every symbol
#: Bytes of long arrays and of queued tuples that a sort holds in memory.
MEMORY = 64 << 20
#: Records sorted, merged or popped at once, and names in a range of symbols.
BLOCK, RANGE = 1 << 17, 1 << 15
SMALL = 1 << 20
NAME = np.uint32
NO_NAME = np.iinfo(NAME).max
TUPLE = np.dtype([("symbol", np.uint32), ("place", np.uint32), ("prefix", np.uint8)])


class Space:
    """Arrays in memory up to a limit of bytes, in temporary files beyond it."""

    def __init__(self, limit: int = MEMORY):
        self.left = limit

    def array(self, n: int, kind) -> np.ndarray:
        size = max(n, 1) * np.dtype(kind).itemsize
        if size <= self.left:
            self.left -= size
            return np.empty(max(n, 1), kind)[:n]
        with tempfile.TemporaryFile() as file:
            file.truncate(size)
            return np.asarray(np.memmap(file, kind, "r+", shape=(max(n, 1),)))[:n]


class Runs:
    """Pairs (key, value) sorted by key: sorted runs on disk beyond ``block`` pairs, merged block by block."""

    def __init__(self, block: int = BLOCK):
        self.block, self.held, self.n = block, [], 0
        self.runs: list[tuple[np.ndarray, np.ndarray]] = []

    def add(self, key: np.ndarray, value: np.ndarray) -> None:
        self.held.append((key.astype(np.uint64, copy=False), value.astype(NAME, copy=False)))
        self.n += len(key)
        if self.n >= self.block:
            self._close_run()

    def _sorted(self) -> tuple[np.ndarray, np.ndarray]:
        key, value = (np.concatenate([h[k] for h in self.held]) for k in (0, 1))
        order = np.argsort(key)
        self.held, self.n = [], 0
        return key[order], value[order]

    def _close_run(self) -> None:
        if self.n:
            key, value = self._sorted()
            with tempfile.TemporaryFile() as file:
                file.write(key.data)
                file.write(value.data)
                file.flush()
                self.runs.append((np.asarray(np.memmap(file, np.uint64, "r", 0, (len(key),))), np.asarray(np.memmap(file, NAME, "r", key.nbytes, (len(key),)))))

    def __iter__(self) -> Iterator[tuple[np.ndarray, np.ndarray]]:
        if not self.runs:
            if self.n:
                yield self._sorted()
            return
        self._close_run()
        live = [[key, value, 0] for key, value in self.runs]
        self.runs = []
        while live:
            step = max(1024, self.block // len(live))
            heads = [key[at : at + step] for key, _, at in live]
            bound = min(h[-1] for h in heads)
            take = [int(np.searchsorted(h, bound, side="right")) for h in heads]
            key = np.concatenate([h[:n] for h, n in zip(heads, take, strict=True)])
            value = np.concatenate([v[at : at + n] for (_, v, at), n in zip(live, take, strict=True)])
            order = np.argsort(key)
            yield key[order], value[order]
            for run, n in zip(live, take, strict=True):
                run[2] += n
            live = [run for run in live if run[2] < len(run[0])]


class RangeQueue:
    """First-in first-out queues of tuples by range of symbols; beyond ``limit`` bytes they lie in one temporary file."""

    def __init__(self, starts: np.ndarray, limit: int = MEMORY, block: int = BLOCK):
        self.starts, self.limit, self.block = starts, limit, block
        self.parts: dict[int, list] = {}
        self.pending: list[np.ndarray] = []
        self.n = self.held = 0
        self.file = None

    def put(self, tuples: np.ndarray) -> None:
        if len(tuples):
            self.pending.append(tuples)
            self.n += len(tuples)
            if self.n > self.block:
                self._deal()

    def _deal(self) -> None:
        if not self.n:
            return
        tuples = np.concatenate(self.pending)
        self.pending, self.n = [], 0
        of = np.searchsorted(self.starts, tuples["symbol"], side="right") - 1
        of = of.astype(np.uint8 if len(self.starts) <= 256 else np.uint32)
        order = np.argsort(of, kind="stable")
        of, tuples = of[order], tuples[order]
        cuts = np.flatnonzero(of[1:] != of[:-1]) + 1
        for a, b in zip([0, *cuts.tolist()], [*cuts.tolist(), len(of)], strict=True):
            self.parts.setdefault(int(of[a]), []).append(tuples[a:b].copy())
        self.held += tuples.nbytes
        if self.held > self.limit:
            self._spill()

    def _spill(self) -> None:
        self.file = self.file or tempfile.TemporaryFile()
        self.file.seek(0, 2)
        for parts in self.parts.values():
            for k, part in enumerate(parts):
                if isinstance(part, np.ndarray):
                    parts[k] = (self.file.tell(), len(part))
                    self.file.write(part.data)
        self.held = 0

    def take(self, k: int) -> np.ndarray | None:
        """The oldest part queued in range ``k``, or None."""
        if not self.parts.get(k):
            self._deal()
        parts = self.parts.get(k)
        if not parts:
            return None
        part = parts.pop(0)
        if isinstance(part, np.ndarray):
            self.held -= part.nbytes
            return part
        at, n = part
        self.file.seek(at)
        return np.frombuffer(self.file.read(n * TUPLE.itemsize), TUPLE)

    def take_all(self, k: int) -> np.ndarray:
        self._deal()
        parts = []
        while (part := self.take(k)) is not None:
            parts.append(part)
        return np.concatenate(parts) if parts else np.zeros(0, TUPLE)

    def close(self) -> None:
        if self.file:
            self.file.close()


class Bytes:
    """The shard's bytes, padded so that a word can be read from every place."""

    def __init__(self, padded: np.ndarray, n: int, depth: int):
        self.n, self.depth = n, depth
        self.text = padded[:n]
        self.word = np.ndarray((len(padded) - 7,), ">u8", padded, 0, (1,))
        self.half = np.ndarray((len(padded) - 3,), ">u4", padded, 0, (1,))

    def common(self, a: np.ndarray, b: np.ndarray) -> np.ndarray:
        """Bytes that the suffixes at ``a`` and ``b`` share, ``depth`` at most."""
        out = np.full(len(a), self.depth, np.int64)
        live = np.arange(len(a))
        last = len(self.word) - 1
        for k in range(0, self.depth, 8):
            x = self.word[np.minimum(a[live] + k, last)].astype(np.uint64) ^ self.word[np.minimum(b[live] + k, last)].astype(np.uint64)
            differ = x != 0
            top = x[differ] >> np.uint64(32)
            bits = np.frexp(np.where(top, top, x[differ]).astype(float))[1] + np.where(top, 32, 0)  # both fit a float
            out[live[differ]] = k + (64 - bits) // 8
            live = live[~differ]
            if not len(live):
                break
        return np.minimum(out, self.depth)


@dataclass
class Level:
    """A string of symbols: bytes at the bottom, names above. ``at``: byte place of each symbol, None at the bottom."""

    text: np.ndarray
    top: int  # the largest symbol
    starts: np.ndarray  # first symbol of each range
    at: np.ndarray | None
    base: Bytes

    def byte(self, place: np.ndarray) -> np.ndarray:
        return place if self.at is None else self.at[place].astype(np.int64)

    def head(self, s: np.ndarray, e: np.ndarray) -> tuple[np.ndarray, int]:
        """The first symbols of the substrings from s to e (included) as a 64-bit key, and how many."""
        if self.at is None:
            short = np.maximum(7 - (e - s), 0).astype(np.uint64)
            return self.base.word[s].astype(np.uint64) | ((np.uint64(1) << (short * np.uint64(8))) - np.uint64(1)), 8
        second = np.where(s < e, self.text[np.minimum(s + 1, len(self.text) - 1)], NO_NAME)
        return (self.text[s].astype(np.uint64) << np.uint64(32)) | second.astype(np.uint64), 2

    def tail(self, s: np.ndarray, e: np.ndarray) -> tuple[np.ndarray, int]:
        """Further symbols from s (one past e at most) as a 32-bit key, and how many."""
        if self.at is None:
            short = np.maximum(3 - (e - s), 0).astype(np.uint64)
            return self.base.half[s].astype(np.uint64) | ((np.uint64(1) << (short * np.uint64(8))) - np.uint64(1)), 4
        return np.where(s <= e, self.text[np.minimum(s, len(self.text) - 1)], NO_NAME).astype(np.uint64), 1


def seed_places(text: np.ndarray, space: Space) -> np.ndarray:
    """Places that are smaller than their successor and follow one that is larger, read in blocks from the end."""
    n = len(text)
    out = space.array(n // 2 + 1, NAME)
    free = len(out)
    rises, z = True, n - 1
    while z > 0:
        a = max(0, z - BLOCK)
        x = np.asarray(text[a : z + 1])
        less, differ = x[:-1] < x[1:], x[:-1] != x[1:]
        m = len(less)
        nxt = np.minimum.accumulate(np.where(differ, np.arange(m), m)[::-1])[::-1]
        up = np.append(np.where(nxt < m, less[np.minimum(nxt, m - 1)], rises), rises)
        s = np.flatnonzero(up[1:] & ~up[:-1]) + (a + 1)
        out[free - len(s) : free] = s
        free -= len(s)
        rises, z = bool(up[0]), a
    return out[free:]


def name_seeds(level: Level, seeds: np.ndarray, names: np.ndarray) -> tuple[bool, list[int]]:
    """Fill ``names``: per seed the place of its substring among all sorted ones. (all differ?, names of over RANGE seeds)"""
    m, last = len(seeds), len(level.text) - 1

    def ends(k: np.ndarray) -> np.ndarray:
        return np.where(k + 1 < m, seeds[np.minimum(k + 1, m - 1)], last).astype(np.int64)

    runs, covered = Runs(), 0
    for a in range(0, m, BLOCK):
        k = np.arange(a, min(a + BLOCK, m))
        key, width = level.head(seeds[k].astype(np.int64), ends(k))
        runs.add(key, k)
    differ, frequent = True, []
    while True:
        nxt = Runs()
        more = False
        index = 0  # pairs seen in this round
        seen: tuple | None = None  # key, group's name, base, where the base began, group's size
        for key, k in runs:
            n = len(key)
            base = key >> np.uint64(32) if covered else np.zeros(n, np.uint64)
            new = np.append(True, key[1:] != key[:-1])
            fresh = np.append(True, base[1:] != base[:-1])
            began = 0
            if seen is not None:
                new[0] = key[0] != seen[0]
                fresh[0] = base[0] != seen[2]
                began = seen[3]
            place = np.arange(index, index + n)
            began = np.maximum.accumulate(np.where(fresh, place, began))
            name = base.astype(np.int64) + place - began
            first = np.maximum.accumulate(np.where(new, np.arange(n), -1))
            name = np.where(first >= 0, name[np.maximum(first, 0)], seen[1] if seen else 0)
            s, e = seeds[k].astype(np.int64), ends(k)
            ended = e - s + 1 < covered + width  # its key shows that it ends: a shorter name is larger than one it begins
            single = new & np.append(new[1:], False)
            done = ended | single
            names[k[done]] = name[done]
            go = ~done
            if go.any():
                more = True
                key2, width2 = level.tail(s[go] + covered + width, e[go])
                nxt.add((name[go].astype(np.uint64) << np.uint64(32)) | key2, k[go])
            differ &= not (ended & ~new).any()
            # Sizes of finished groups, also of those that go on over blocks.
            cuts = np.flatnonzero(new)
            sizes = np.diff(np.append(cuts, n))
            size = (seen[4] if seen else 0) + (int(cuts[0]) if len(cuts) else n)
            if size > RANGE and seen is not None and seen[1] not in frequent:
                frequent.append(seen[1])
            frequent += [int(x) for x in name[cuts[sizes > RANGE]]]
            size = int(sizes[-1]) if len(cuts) else size
            seen = (key[-1], int(name[-1]), base[-1], int(began[-1]), size)
            index += n
        if not more:
            return differ, sorted(set(frequent))
        covered += width
        width = width2
        runs = nxt


def range_minima(values: np.ndarray, lo: np.ndarray, hi: np.ndarray) -> np.ndarray:
    """The least of values[lo:hi] for each pair (lo < hi), by minima over powers of two."""
    out = np.empty(len(lo), values.dtype)
    power = (np.frexp((hi - lo).astype(float))[1] - 1).astype(np.uint8)
    order = np.argsort(power, kind="stable")
    ends = np.cumsum(np.bincount(power, minlength=1))
    table, width, a = values, 1, 0
    for b in ends.tolist():
        pick = order[a:b]
        out[pick] = np.minimum(table[lo[pick]], table[hi[pick] - width])
        if b < len(order):
            table = np.minimum(table[:-width], table[width:])
            width, a = 2 * width, b
    return out


class Scan:
    """One inducing scan, upwards or downwards.

    ``known`` gives (places, prefixes) number a to b of the suffixes known before, in scan order;
    within a symbol they follow the induced ones. ``sink`` gets what is popped, in order: places,
    prefixes shared with the one before, and whether each was induced.
    """

    def __init__(self, level: Level, known: Callable, n_known: int, down: bool, sink: Callable, space: Space, memory: int):
        self.level, self.known, self.n_known, self.down, self.sink = level, known, n_known, down, sink
        starts = level.starts
        ends = np.append(starts[1:], level.top + 1)
        self.starts = (level.top + 1 - ends)[::-1] if down else starts
        self.ends = (level.top + 1 - starts)[::-1] if down else ends
        self.queue = RangeQueue(self.starts, memory)
        # Least prefix popped since a symbol's last push: in that batch (since), in later ones (least, from batch when + 1).
        self.since, self.when = space.array(level.top + 1, np.uint8), space.array(level.top + 1, np.uint32)
        self.since[:], self.when[:] = level.base.depth, 0
        self.least, self.batches = np.full(1024, level.base.depth, np.uint8), 0
        self.at, self.ahead = 0, (np.zeros(0, np.int64),) * 3  # known suffixes that were read and not popped yet
        self.last: tuple[int, int] | None = None  # key and place of the last one popped

    def symbol(self, place: np.ndarray) -> np.ndarray:
        x = self.level.text[place].astype(np.int64)
        return self.level.top - x if self.down else x

    def run(self) -> None:
        for k, (lo, hi) in enumerate(zip(self.starts.tolist(), self.ends.tolist(), strict=True)):
            if hi - lo == 1:
                self._one_symbol(k, lo)
            else:
                self._range(k, hi)
        self.queue.close()

    def _next_known(self, hi: int) -> tuple[np.ndarray, np.ndarray, np.ndarray] | None:
        """Symbols, places and prefixes of the next known suffixes below symbol ``hi``."""
        if not len(self.ahead[0]):
            if self.at == self.n_known:
                return None
            end = min(self.at + BLOCK, self.n_known)
            places, prefixes = self.known(self.at, end)
            self.at, self.ahead = end, (self.symbol(places), places, prefixes)
        n = int(np.searchsorted(self.ahead[0], hi))
        now, self.ahead = tuple(x[:n] for x in self.ahead), tuple(x[n:] for x in self.ahead)
        return now if n else None

    def _one_symbol(self, k: int, symbol: int) -> None:
        while (part := self.queue.take(k)) is not None:
            self.queue.put(self._pop(np.full(len(part), 2 * symbol), part["place"].astype(np.int64), part["prefix"]))
        while (known := self._next_known(symbol + 1)) is not None:
            _, places, prefixes = known
            self.queue.put(self._pop(np.full(len(places), 2 * symbol + 1), places, prefixes))

    def _range(self, k: int, hi: int) -> None:
        part = self.queue.take_all(k)
        keys, places, prefixes = [2 * part["symbol"].astype(np.int64)], [part["place"].astype(np.int64)], [part["prefix"]]
        while (known := self._next_known(hi)) is not None:
            keys.append(2 * known[0] + 1)
            places.append(known[1])
            prefixes.append(known[2])
        key, place, prefix = (np.concatenate(x) for x in (keys, places, prefixes))
        order = np.argsort(key, kind="stable")
        key, place, prefix = key[order], place[order], prefix[order]
        size = 256
        while len(key):
            a = key[:size]
            target = self._targets(a, place[:size])
            least = np.minimum.accumulate(np.where(target >= 0, 2 * target, np.iinfo(np.int64).max))
            unsafe = np.flatnonzero(least[:-1] < a[1:])
            n = int(unsafe[0]) + 1 if len(unsafe) else len(a)
            size = min(max(256, 2 * n), BLOCK)
            pushed = self._pop(a[:n], place[:n], prefix[:n], target[:n])
            key, place, prefix = key[n:], place[n:], prefix[n:]
            here = pushed["symbol"] < hi
            if here.any():
                now = pushed[here]  # sorted by symbol, in order of arrival
                new = 2 * now["symbol"].astype(np.int64)
                to = np.searchsorted(key, new, side="right") + np.arange(len(new))
                old = np.ones(len(key) + len(new), bool)
                old[to] = False
                merged = []
                for x, y in ((key, new), (place, now["place"]), (prefix, now["prefix"])):
                    z = np.empty(len(old), x.dtype)
                    z[old], z[to] = x, y
                    merged.append(z)
                key, place, prefix = merged
                pushed = pushed[~here]
            self.queue.put(pushed)

    def _targets(self, key: np.ndarray, place: np.ndarray) -> np.ndarray:
        """The symbol under which each one's predecessor is induced; -1 where it is not."""
        t = self.symbol(np.maximum(place - 1, 0))
        symbol = key >> 1
        return np.where((place > 0) & ((t > symbol) | ((t == symbol) & (key & 1 == 0))), t, -1)

    def _pop(self, key: np.ndarray, place: np.ndarray, prefix: np.ndarray, target: np.ndarray | None = None) -> np.ndarray:
        """Take a batch in order; returns the tuples that it induces, by symbol and in order of arrival."""
        level, n = self.level, len(key)
        edge = np.append(True, key[1:] != key[:-1])
        if self.last is not None:
            edge[0] = key[0] != self.last[0]
        prefix = np.array(prefix, np.uint8)
        cut = np.flatnonzero(edge)
        if len(cut):
            before = np.where(cut > 0, place[cut - 1], self.last[1] if self.last else place[0])
            other = np.where(cut > 0, key[cut - 1], self.last[0] if self.last else -2)
            fixed = np.zeros(len(cut), np.int64)
            ask = np.flatnonzero((other >> 1 == key[cut] >> 1) if level.at is None else other >= 0)
            if len(ask):
                fixed[ask] = level.base.common(level.byte(before[ask]), level.byte(place[cut[ask]]))
            prefix[cut] = fixed
        self.last = int(key[-1]), int(place[-1])
        self.sink(place, prefix, key & 1 == 0)
        if target is None:
            target = self._targets(key, place)
        idx = np.flatnonzero(target >= 0)
        t = target[idx]
        order = np.argsort(t.astype(np.uint8) if level.top < 256 else t, kind="stable")
        idx, t = idx[order], t[order]
        m = len(idx)
        here = self.batches
        if here + 2 > len(self.least):
            self.least = np.append(self.least, np.full(len(self.least), level.base.depth, np.uint8))
        running = np.minimum.accumulate(prefix)
        if m:
            lead = np.append(True, t[1:] != t[:-1])
            head, rest = np.flatnonzero(lead), np.flatnonzero(~lead)
            first = t[head]
            shared = np.empty(m, np.uint8)
            shared[head] = np.minimum(np.minimum(self.since[first], self.least[self.when[first]]), running[idx[head]])
            if len(rest):
                shared[rest] = range_minima(prefix, idx[rest - 1] + 1, idx[rest] + 1)
            tail = idx[np.append(head[1:] - 1, m - 1)]
            back = np.append(np.minimum.accumulate(prefix[::-1])[::-1], np.uint8(level.base.depth))
            self.since[first], self.when[first] = back[tail + 1], here + 1
        np.minimum(self.least[: here + 1], running[-1], out=self.least[: here + 1])
        self.batches = here + 1
        if not m:
            return np.zeros(0, TUPLE)
        i = place[idx] - 1
        step = 1 if level.at is None else level.byte(place[idx]) - level.byte(i)
        out = np.empty(m, TUPLE)
        out["symbol"], out["place"] = t, i
        out["prefix"] = np.minimum(shared.astype(np.int64) + step, level.base.depth)
        return out


def doubled_order(names: np.ndarray) -> np.ndarray:
    """Suffix order of a short string of names that ends with its only smallest one; a name is the place of its group."""
    m = len(names)
    rank = names.astype(np.int64)
    step = 1
    while True:
        idx = np.flatnonzero(np.bincount(rank, minlength=m)[rank] > 1)
        if not len(idx):
            break
        key = (rank[idx] << 32) | rank[idx + step]  # the last name differs from all others, so idx + step exists
        by = np.argsort(key)
        order, key = idx[by], key[by]
        base, at = key >> 32, np.arange(len(key))
        group = np.maximum.accumulate(np.where(np.append(True, base[1:] != base[:-1]), at, 0))
        place = np.maximum.accumulate(np.where(np.append(True, key[1:] != key[:-1]), at, 0))
        rank[order] = base + place - group
        step *= 2
    out = np.empty(m, NAME)
    out[rank] = np.arange(m)
    return out


def _sort(level: Level, emit: Callable, space: Space, memory: int) -> None:
    """All places of a level in falling order of their suffixes, with prefixes, in blocks to ``emit``."""
    n, left = len(level.text), space.left
    if n == 1:
        emit(np.zeros(1, np.int64), np.zeros(1, np.uint8))
        return
    seeds = seed_places(level.text, space)
    m = len(seeds)
    order, prefixes = space.array(m, NAME), space.array(m, np.uint8)
    inner = space.left
    names = space.array(m, NAME)
    differ, frequent = name_seeds(level, seeds, names)
    if differ or m <= SMALL:
        if differ:
            for a in range(0, m, BLOCK):
                order[names[a : a + BLOCK]] = np.arange(a, min(a + BLOCK, m))
        else:
            order[:] = doubled_order(names)
        for a in range(0, m, BLOCK):  # the recursion ends: neighbours are compared
            now = level.byte(seeds[order[max(a - 1, 0) : a + BLOCK]].astype(np.int64))
            prefixes[a] = 0
            prefixes[max(a, 1) : a + BLOCK] = level.base.common(now[:-1], now[1:])
    else:
        starts = np.unique(np.concatenate([np.arange(0, m, RANGE), frequent, np.array(frequent) + 1]).astype(np.int64))
        if level.at is None:
            at = seeds
        else:
            at = space.array(m, NAME)
            for a in range(0, m, BLOCK):
                at[a : a + BLOCK] = level.at[seeds[a : a + BLOCK]]
        upper = Level(names, m - 1, starts[starts < m], at, level.base)
        free = m

        def keep(place: np.ndarray, prefix: np.ndarray) -> None:
            """Turn the falling order round; a prefix belongs to the larger one of a pair then."""
            nonlocal free
            k = len(place)
            order[free - k : free] = place[::-1]
            # prefix[x] is shared with the one before in falling order, which stands one further up now.
            up = np.arange(free, free - k, -1)
            ok = up < m
            prefixes[up[ok]] = prefix[ok]
            free -= k

        _sort(upper, keep, space, memory)
        prefixes[0] = 0
    space.left = inner
    del names
    n_falls = 0
    falls, shared = space.array(n, NAME), space.array(n, np.uint8)

    def fall(place: np.ndarray, prefix: np.ndarray, induced: np.ndarray) -> None:
        nonlocal n_falls
        k = int(induced.sum())
        falls[n_falls : n_falls + k] = place[induced]
        shared[n_falls : n_falls + k] = prefix[induced]
        n_falls += k

    def known_seeds(a: int, b: int) -> tuple[np.ndarray, np.ndarray]:
        return seeds[order[a:b]].astype(np.int64), prefixes[a:b]

    here = space.left
    Scan(level, known_seeds, m, False, fall, space, memory).run()
    space.left = here

    def known_falls(a: int, b: int) -> tuple[np.ndarray, np.ndarray]:
        places = falls[n_falls - b : n_falls - a][::-1].astype(np.int64)
        prefix = np.zeros(b - a, np.uint8)
        first = 1 if a == 0 and b > a else 0
        prefix[first:] = shared[n_falls - b + 1 : n_falls - a + 1 - first][::-1]
        return places, prefix

    Scan(level, known_falls, n_falls, True, lambda place, prefix, _: emit(place, prefix), space, memory).run()
    emit(np.array([n - 1]), np.zeros(1, np.uint8))
    space.left = left


def suffix_blocks(padded: np.ndarray, n: int, emit: Callable, depth: int = DEPTH, memory: int = MEMORY) -> None:
    """Hand ``emit`` blocks (places, prefixes) of all suffixes in falling order.

    ``padded``: uint8, ``n`` symbols of which the last one is the only zero, and eight more bytes. A prefix
    counts the bytes shared with the suffix handed over before, ``depth`` (at most 255) at most.
    """
    if n >= NO_NAME:
        raise ValueError("a shard holds at most 2**32 - 2 bytes")
    base = Bytes(padded, n, depth)
    _sort(Level(base.text, 255, np.arange(256), None, base), emit, Space(memory), memory)


def suffix_order(text: np.ndarray, depth: int = DEPTH, memory: int = MEMORY) -> tuple[np.ndarray, np.ndarray]:
    """Start places in rising order of their suffixes, and the prefix that each shares with the one before."""
    blocks: list[tuple[np.ndarray, np.ndarray]] = []
    suffix_blocks(np.append(text, np.zeros(8, np.uint8)), len(text), lambda a, b: blocks.append((a, b)), depth, memory)
    place, prefix = (np.concatenate([b[k] for b in blocks])[::-1] for k in (0, 1))
    return place, np.append(np.uint8(0), prefix[:-1])
