"""Suffix arrays with common prefixes by recursive induced sorting, with texts, queues and results on disk.

Suffixes that are smaller than their successor but follow one that is not (the sampled suffixes) are sorted first; all
others follow by induction: scanning suffixes in order, each suffix places the one that starts a symbol earlier. What
waits for its turn is in a priority queue by first symbol. Suffixes of a symbol enter the queue in their final order, so
a queue is a first-in-first-out list for each symbol. A tuple in the queue is a position and the length of the prefix
that it shares with the tuple before it, which is carried along: one more than the least shared prefix among the
suffixes scanned between the two that placed them.

The sampled suffixes are sorted by recursion: the same induction sorts the stretches between sampled positions, equal
stretches get equal names, and the sequence of names is sorted in turn, until names are unique (or most are, and the
rest fits into memory: these are told apart by what follows). A text of names has too
many symbols for a list each: while memory allows, its suffixes are placed all at once, by ranks; beyond it, its queue
holds what fits into memory and writes the rest as runs in order of symbols, which are merged when they are read. Prefixes are carried on the lowest level alone, which asks for them.

A sort has `limit` bytes for what grows with its text. Arrays beyond it lie in files, queues beyond it spill, scans work
in pieces, and results come as a stream, so a text may be far larger than memory. Shared prefixes are counted up to a
cap, which lets a range minimum be answered from byte-sized tables.
"""

from __future__ import annotations

import tempfile
from collections.abc import Iterator

import numpy as np

#: Bytes for what grows with the text; beyond it, arrays and tuples go to disk.
LIMIT = 64 << 20
#: Suffixes that a scan meets at a time.
PIECE = 1 << 18
#: Names that occur so many times or fewer on average end the recursion, if what that takes fits into memory; and bytes
#: that always do.
ALONE, FEW = 1.5, 1 << 14
#: Bytes for each name that inducing at once takes.
AT_ONCE = 80


class Room:
    """Memory of a sort: arrays while the limit lasts, files beyond it. spilled: bytes on disk by level of recursion."""

    def __init__(self, limit: int = LIMIT):
        self.limit, self.held, self.spilled = limit, 0, {}

    def array(self, n: int, kind, level: int) -> np.ndarray:
        size = n * np.dtype(kind).itemsize
        if self.held + size <= self.limit // 2 or not n:
            self.held += size
            return np.empty(n, dtype=kind)
        self.note(size, level)
        file = tempfile.TemporaryFile(prefix="edgefold-sort-")
        file.truncate(size)
        return np.memmap(file, dtype=kind, mode="r+", shape=(n,))

    def give_back(self, *arrays: np.ndarray) -> None:
        """These arrays are no longer used."""
        self.held -= sum(a.nbytes for a in arrays if not isinstance(a, np.memmap))

    def note(self, size: int, level: int) -> None:
        self.spilled[level] = self.spilled.get(level, 0) + size


class Spool:
    """Pieces of (position, shared prefix), in memory up to a limit, then in a file."""

    def __init__(self, room: Room, level: int):
        self.room, self.level, self.held, self.file = room, level, 0, None

    def put(self, positions: np.ndarray, shared: np.ndarray):
        size = positions.nbytes + shared.nbytes
        if self.held + size <= self.room.limit // 4:
            self.held += size
            return positions, shared
        if self.file is None:
            self.file = tempfile.TemporaryFile(prefix="edgefold-queue-")
        at = self.file.seek(0, 2)
        self.file.write(positions.tobytes())
        self.file.write(shared.tobytes())
        self.room.note(size, self.level)
        return at, len(positions), positions.dtype

    def get(self, item) -> tuple[np.ndarray, np.ndarray]:
        """A piece that was put, which is given up by it."""
        if len(item) == 2:
            self.held -= item[0].nbytes + item[1].nbytes
            return item
        at, n, kind = item
        self.file.seek(at)
        positions = np.frombuffer(self.file.read(n * kind.itemsize), dtype=kind)
        return positions, np.frombuffer(self.file.read(n), dtype=np.uint8)

    def close(self) -> None:
        if self.file is not None:
            self.file.close()


class DiskQueue:
    """First-in-first-out lists of (position, shared prefix) for each symbol."""

    def __init__(self, symbols: int, room: Room, level: int = 0):
        self.lists: list[list] = [[] for _ in range(symbols)]
        self.spool = Spool(room, level)

    def put(self, symbol: int, positions: np.ndarray, shared: np.ndarray) -> None:
        self.lists[symbol].append(self.spool.put(positions, shared))

    def take(self, symbol: int):
        """What waits for a symbol, in order, up to a piece of it; None if nothing does."""
        waiting, got, size = self.lists[symbol], [], 0
        while waiting and size < PIECE:
            got.append(self.spool.get(waiting.pop(0)))
            size += len(got[-1][0])
        if not got:
            return None
        return got[0] if len(got) == 1 else (np.concatenate([p for p, _ in got]), np.concatenate([s for _, s in got]))

    def close(self) -> None:
        self.spool.close()


class NameQueue:
    """First-in-first-out lists of positions for very many symbols, which are asked for in order (or in reverse order).

    Lists beyond the limit are written as a run, by symbol in the order of asking; runs are read in step with the asking.
    """

    def __init__(self, descending: bool, room: Room, level: int):
        self.descending, self.room, self.level = descending, room, level
        self.lists: dict[int, list[int]] = {}
        self.held, self.most = 0, max(64, room.limit // 64)  # an item takes some tens of bytes
        self.file, self.runs = None, []

    def spill(self) -> None:
        order = sorted(self.lists, reverse=self.descending)
        sizes = [len(self.lists[s]) for s in order]
        pairs = np.empty((sum(sizes), 2), dtype=np.int64)
        pairs[:, 0] = np.repeat(order, sizes)
        pairs[:, 1] = np.fromiter((p for s in order for p in self.lists[s]), np.int64, len(pairs))
        if self.file is None:
            self.file = tempfile.TemporaryFile(prefix="edgefold-names-")
        self.runs.append(_Run(self.file, self.file.seek(0, 2), len(pairs)))
        self.file.write(pairs.tobytes())
        self.room.note(pairs.nbytes, self.level)
        self.lists.clear()
        self.held = 0

    def take(self, symbol: int) -> list[int] | None:
        """Some of what waits for the symbol, in order; None if nothing does."""
        for k, run in enumerate(self.runs):
            if run.symbol() == symbol:
                got = run.take()
                if run.symbol() is None:
                    self.runs.pop(k)
                return got
        got = self.lists.pop(symbol, None)
        if got:
            self.held -= len(got)
        return got

    def close(self) -> None:
        if self.file is not None:
            self.file.close()


class _Run:
    """Pairs (symbol, position) in a file, read block by block."""

    def __init__(self, file, at: int, n: int, block: int = 4_096):
        self.file, self.at, self.left, self.block = file, at, n, block
        self.pairs, self.next = None, 0

    def symbol(self) -> int | None:
        if self.pairs is None or self.next == len(self.pairs):
            n = min(self.left, self.block)
            if not n:
                return None
            self.file.seek(self.at)
            self.pairs, self.next = np.frombuffer(self.file.read(16 * n), dtype=np.int64).reshape(n, 2), 0
            self.at, self.left = self.at + 16 * n, self.left - n
        return int(self.pairs[self.next, 0])

    def take(self) -> list[int]:
        """The positions of the first symbol in this block."""
        rest = self.pairs[self.next :]
        other = np.flatnonzero(rest[:, 0] != rest[0, 0])
        n = int(other[0]) if len(other) else len(rest)
        self.next += n
        return rest[:n, 1].tolist()


def shared_prefix(text: np.ndarray, a: np.ndarray, b: np.ndarray, cap: int) -> np.ndarray:
    """Length of the common prefix of the suffixes at a and b, up to the cap; past its end a text differs from all."""
    n, out = len(text), np.zeros(len(a), dtype=np.int64)
    active = np.arange(len(a))
    for step in range(cap):
        i, j = a[active] + step, b[active] + step
        inside = (i < n) & (j < n)
        same = inside.copy()
        same[inside] = text[i[inside]] == text[j[inside]]
        active = active[same]
        if not len(active):
            break
        out[active] = step + 1
    return out.astype(np.uint8)


class _Minima:
    """Range minima of byte-sized values."""

    def __init__(self, values: np.ndarray, longest: int):
        self.rows = [values]
        while (1 << len(self.rows)) <= longest:
            half = 1 << (len(self.rows) - 1)
            last = self.rows[-1]
            self.rows.append(np.minimum(last[:-half], last[half:]) if len(last) > half else last[:0])

    def of(self, low: np.ndarray, high: np.ndarray) -> np.ndarray:
        """Least value in low..high, both included."""
        size = high - low + 1
        level = np.frexp(size.astype(np.float64))[1] - 1
        out = np.empty(len(low), dtype=np.uint8)
        for k in np.unique(level).tolist():
            m = level == k
            row = self.rows[k]
            out[m] = np.minimum(row[low[m]], row[high[m] - (1 << k) + 1])
        return out


def _spans(n: int) -> Iterator[tuple[int, int]]:
    return ((a, min(n, a + PIECE)) for a in range(0, n, PIECE))


def kinds(text: np.ndarray, room: Room, level: int) -> np.ndarray:
    """True where a suffix is smaller than its successor."""
    n = len(text)
    out, after = room.array(n, bool, level), False
    for a, e in reversed(list(_spans(n))):
        part = text[a : e + 1].astype(np.int64)
        step = np.zeros(e - a, dtype=np.int8)
        step[: len(part) - 1] = np.sign(part[1:] - part[:-1])
        if e == n:
            step[-1] = -1
        near = np.where(step != 0, np.arange(e - a), e - a)
        near = np.minimum.accumulate(near[::-1])[::-1]
        known = near < e - a
        out[a:e] = np.where(known, step[np.where(known, near, 0)] > 0, after)
        after = bool(out[a])
    return out


class _Scan:
    """One scan of the induction: what it meets, in order, places its predecessors of one kind."""

    def __init__(self, text, smaller, kind: bool, symbols: int, cap: int, room: Room):
        self.text, self.smaller, self.kind, self.cap = text, smaller, kind, cap
        self.queue = DiskQueue(symbols, room)
        self.since = np.full(symbols, cap, dtype=np.uint8)  # least shared prefix since the last placed suffix
        self.fresh = np.ones(symbols, dtype=bool)

    def meet(self, positions: np.ndarray, shared: np.ndarray) -> None:
        """shared: with what was met just before."""
        before = positions - 1
        ok = np.flatnonzero((before >= 0) & (self.smaller[np.maximum(before, 0)] == self.kind))
        least = int(shared.min())
        if not len(ok):
            np.minimum(self.since, least, out=self.since)
            return
        symbol = self.text[before[ok]]
        order = np.argsort(symbol, kind="stable")
        at, symbol = ok[order], symbol[order]
        first = np.ones(len(at), dtype=bool)
        first[1:] = symbol[1:] != symbol[:-1]
        if self.cap == 1:  # prefixes are not asked for
            heads = np.flatnonzero(first)
            self._place(symbol[heads].tolist(), heads, before[at], np.zeros(len(at), dtype=np.uint8))
            return
        low = np.empty(len(at), dtype=np.int64)
        low[0], low[1:] = 0, at[:-1] + 1
        low[first] = 0
        minima = _Minima(shared, int(max((at - low).max() + 1, len(shared) - int(at.min()))))
        got = minima.of(low, at)
        heads = np.flatnonzero(first)
        present = symbol[heads].astype(np.int64)
        got[heads] = np.minimum(got[heads], self.since[present])
        carried = np.minimum(got.astype(np.int16) + 1, self.cap).astype(np.uint8)
        carried[heads[self.fresh[present]]] = 0
        np.minimum(self.since, least, out=self.since)
        ends = np.append(heads[1:], len(at))
        tails = at[ends - 1]
        rest = tails + 1 < len(shared)
        self.since[present] = self.cap
        if rest.any():
            self.since[present[rest]] = minima.of(tails[rest] + 1, np.full(int(rest.sum()), len(shared) - 1))
        self.fresh[present] = False
        self._place(present.tolist(), heads, before[at], carried)

    def _place(self, symbols: list[int], heads: np.ndarray, placed: np.ndarray, carried: np.ndarray) -> None:
        for s, a, e in zip(symbols, heads.tolist(), [*heads[1:].tolist(), len(placed)], strict=True):
            self.queue.put(s, placed[a:e], carried[a:e])


def _first_symbols(text: np.ndarray, sampled: np.ndarray, symbols: int) -> np.ndarray:
    """Where each symbol's sampled suffixes begin, if these are in order of their first symbols."""
    count = np.zeros(symbols, dtype=np.int64)
    for a, e in _spans(len(sampled)):
        count += np.bincount(text[sampled[a:e]], minlength=symbols)
    return np.concatenate([[0], np.cumsum(count)])


def induce(text, smaller, sampled, shared, symbols: int, cap: int, room: Room) -> Iterator[tuple[np.ndarray, np.ndarray]]:
    """All suffixes from the sampled ones, the largest first: positions, and the prefix each shares with the one before.

    sampled must be in order; shared (with the sampled suffix before) belongs to it. With a cap of 1, prefixes mean nothing.
    """
    cuts = _first_symbols(text, sampled, symbols)
    larger, kept = [[] for _ in range(symbols)], Spool(room, 0)
    scan = _Scan(text, smaller, False, symbols, cap, room)
    scan.meet(np.asarray([len(text)], dtype=sampled.dtype), np.zeros(1, dtype=np.uint8))

    def seam(a: int, b: int) -> int:
        return int(shared_prefix(text, np.asarray([a]), np.asarray([b]), cap)[0])

    for c in range(symbols):
        last = -1
        while (got := scan.queue.take(c)) is not None:
            larger[c].append(kept.put(*got))
            last = int(got[0][-1])
            scan.meet(*got)
        for a in range(int(cuts[c]), int(cuts[c + 1]), PIECE):
            e = min(int(cuts[c + 1]), a + PIECE)
            part = np.array(shared[a:e])
            if a == cuts[c]:
                part[0] = seam(last, int(sampled[a])) if last >= 0 else 0
            scan.meet(np.asarray(sampled[a:e]), part)
    scan.queue.close()
    scan = _Scan(text, smaller, True, symbols, cap, room)
    for c in range(symbols - 1, -1, -1):
        last = -1
        while (got := scan.queue.take(c)) is not None:
            last = int(got[0][-1])
            scan.meet(*got)
            yield got
        above = None  # what the last suffix of a piece shares with the one that was met before
        while larger[c]:
            p, s = kept.get(larger[c].pop())
            back = np.empty_like(s)
            back[1:] = s[:0:-1]
            back[0] = above if above is not None else seam(int(p[-1]), last) if last >= 0 else 0
            above = s[0]
            scan.meet(p[::-1], back)
            yield p[::-1], back
    scan.queue.close()
    kept.close()


def induce_names(text, smaller, sampled, symbols: int, room: Room, level: int) -> Iterator[np.ndarray]:
    """Positions of all suffixes of a text of very many symbols, the largest first, from the sampled ones in order.

    Texts that leave memory enough are induced at once; others through queues on disk.
    """
    if len(text) * AT_ONCE <= room.limit:
        yield _induce_at_once(text, smaller, sampled)[::-1]
        return
    t, small, n = memoryview(text), memoryview(smaller), len(text)
    cuts = _first_symbols(text, sampled, symbols).tolist()
    bounds = room.array(symbols + 1, np.int64, level)
    larger = room.array(n - int(np.count_nonzero(smaller)), sampled.dtype, level)

    def feed(queue: NameQueue, kind: bool, piece) -> None:
        lists, put = queue.lists, 0
        for p in piece:
            q = p - 1
            if q >= 0 and small[q] == kind:
                put += 1
                s = t[q]
                if s in lists:
                    lists[s].append(q)
                else:
                    lists[s] = [q]
        queue.held += put
        if queue.held > queue.most:
            queue.spill()

    queue, at, found = NameQueue(False, room, level), 0, []
    lists, runs = queue.lists, queue.runs
    feed(queue, False, [n])
    piece, low = sampled[:PIECE].tolist(), 0  # the sampled positions in hand, and where they begin
    for c in range(symbols):
        bounds[c] = at + len(found)
        while (c in lists) or runs:
            got = queue.take(c)
            if not got:
                break
            found += got
            feed(queue, False, got)
        a, e = cuts[c], cuts[c + 1]
        while a < e:
            if a - low >= len(piece):
                low = a
                piece = sampled[a : a + PIECE].tolist()
            mine = piece[a - low : e - low]
            feed(queue, False, mine)
            a += len(mine)
        if len(found) >= PIECE:
            larger[at : at + len(found)] = found
            at += len(found)
            found = []
    larger[at : at + len(found)] = found
    bounds[symbols] = at + len(found)
    queue.close()
    queue, out = NameQueue(True, room, level), []
    lists, runs = queue.lists, queue.runs
    piece, low = [], int(bounds[symbols])  # the larger positions in hand, and where they begin
    begins = bounds.tolist()
    for c in range(symbols - 1, -1, -1):
        while (c in lists) or runs:
            got = queue.take(c)
            if not got:
                break
            out += got
            feed(queue, True, got)
        a, e = begins[c], begins[c + 1]
        while e > a:
            if e <= low:
                low = max(0, e - PIECE)
                piece = larger[low:e].tolist()
            mine = piece[max(a, low) - low : e - low]
            mine.reverse()
            out += mine
            feed(queue, True, mine)
            e -= len(mine)
        if len(out) >= PIECE:
            yield np.asarray(out, dtype=sampled.dtype)
            out = []
    if out:
        yield np.asarray(out, dtype=sampled.dtype)
    queue.close()
    room.give_back(bounds, larger)


def _induce_at_once(text, smaller, sampled) -> np.ndarray:
    """All suffixes in order. What a scan places is ordered by its symbol and then by the suffix that places it, a position
    later; so ranks by symbol are refined by the ranks of what is 1, 2, 4 positions later, until all differ."""
    t, n = np.asarray(text, dtype=np.int64), len(text)

    def ranks(fixed: np.ndarray, free: np.ndarray, late: bool) -> np.ndarray:
        """fixed: in order; free: placed by these, before (or late: after) those of their symbol. The text's end is least."""
        items = np.concatenate([fixed, free] if late else [free, fixed])
        items = items[np.argsort(t[items], kind="stable")]
        rank, is_free = np.zeros(n + 1, dtype=np.int64), np.zeros(n, dtype=bool)
        rank[items], is_free[free] = np.arange(1, len(items) + 1), True
        at, symbol = np.flatnonzero(is_free[items]), t[items]
        tied, step = items[at], 1
        head = np.concatenate([[True], symbol[at[1:]] != symbol[at[:-1]]])[: len(at)]
        rank[tied] = np.maximum.accumulate(np.where(head, at, 0)) + 1
        while len(tied):
            a, b = rank[tied], rank[tied + step]
            order = np.lexsort((b, a))
            tied, a, b = tied[order], a[order], b[order]
            group = np.concatenate([[True], a[1:] != a[:-1]])
            new = group | np.concatenate([[True], b[1:] != b[:-1]])
            here = np.arange(len(tied))
            rank[tied] = a + np.maximum.accumulate(np.where(new, here, 0)) - np.maximum.accumulate(np.where(group, here, 0))
            tied = tied[~(new & np.concatenate([new[1:], [True]]))]
            step *= 2
        return rank

    larger = np.flatnonzero(~smaller)
    larger = larger[np.argsort(ranks(np.asarray(sampled), larger, False)[larger])]
    out = np.empty(n, dtype=sampled.dtype)
    out[ranks(larger, np.flatnonzero(smaller), True)[:n] - 1] = np.arange(n)
    return out


def _sampled(smaller: np.ndarray, kind, room: Room, level: int) -> np.ndarray:
    """Positions of suffixes that are smaller than their successor and follow one that is not."""
    n, at = len(smaller) - 1, 0
    out = room.array(sum(int(np.count_nonzero(smaller[a + 1 : e + 1] & ~smaller[a:e])) for a, e in _spans(n)), kind, level)
    for a, e in _spans(n):
        part = np.flatnonzero(smaller[a + 1 : e + 1] & ~smaller[a:e]) + (a + 1)
        out[at : at + len(part)] = part
        at += len(part)
    return out


def _by_symbol(text: np.ndarray, sampled: np.ndarray, symbols: int, room: Room, level: int) -> np.ndarray:
    """The sampled positions in order of their first symbol, otherwise as they are."""
    out, place = room.array(len(sampled), sampled.dtype, level), _first_symbols(text, sampled, symbols)[:-1].copy()
    for a, e in _spans(len(sampled)):
        symbol = text[sampled[a:e]]
        order = np.argsort(symbol, kind="stable")
        symbol = symbol[order].astype(np.int64)
        heads = np.flatnonzero(np.concatenate([[True], symbol[1:] != symbol[:-1]]))
        count = np.diff(np.append(heads, len(symbol)))
        out[place[symbol] + np.arange(len(symbol)) - np.repeat(heads, count)] = sampled[a:e][order]
        place[symbol[heads]] += count
    return out


def _sorted_samples(text: np.ndarray, sampled: np.ndarray, rough: Iterator[np.ndarray], room: Room, level: int) -> np.ndarray:
    """The sampled positions in order of their suffixes. rough: all positions by stretches, the largest first."""
    n, m = len(text), len(sampled)
    number = room.array(n, sampled.dtype, level)
    number[:] = -1
    for a, e in _spans(m):
        number[sampled[a:e]] = np.arange(a, e)
    by_stretch, at = room.array(m, sampled.dtype, level), m
    for positions in rough:
        of = number[positions[::-1]]
        of = of[of >= 0]
        by_stretch[at - len(of) : at] = of
        at -= len(of)
    room.give_back(number)
    del number
    names, name, previous = room.array(m, np.int32 if m < 2**31 else np.int64, level + 1), 0, None

    def length(of: np.ndarray) -> np.ndarray:
        after = sampled[np.minimum(of + 1, m - 1)].astype(np.int64)
        return np.where(of + 1 < m, after, n) - sampled[of]

    for a, e in _spans(m):
        of = np.asarray(by_stretch[a:e]) if previous is None else np.concatenate([[previous], by_stretch[a:e]])
        size, p = length(of), sampled[of].astype(np.int64)
        same = size[1:] == size[:-1]
        same[same] = _equal(text, p[:-1][same], p[1:][same], size[1:][same] + 1)
        new = np.concatenate([[name], name + np.cumsum(~same)])
        names[of] = new
        name, previous = int(new[-1]), int(of[-1])
    order = by_stretch if name == m - 1 else sort_names(names, name + 1, room, level + 1)
    out = room.array(m, sampled.dtype, level)
    for a, e in _spans(m):
        out[a:e] = sampled[order[a:e]]
    room.give_back(names, by_stretch, *([] if order is by_stretch else [order]))
    return out


def sort_names(names: np.ndarray, symbols: int, room: Room, level: int = 1) -> np.ndarray:
    """Order of the suffixes of a sequence of the names 0..symbols - 1, by the same recursion; once most of them occur
    a single time, by their ranks and those of what follows, of twice as many names each time."""
    if len(names) < ALONE * symbols and len(names) * 40 <= max(room.limit, FEW):
        return _double(names)
    smaller = kinds(names, room, level)
    kind = np.int32 if len(names) < 2**31 - 1 else np.int64
    sampled = _sampled(smaller, kind, room, level)
    if len(sampled) > 1:
        start = _by_symbol(names, sampled, symbols, room, level)
        sampled = _sorted_samples(names, sampled, induce_names(names, smaller, start, symbols, room, level), room, level)
        room.give_back(start)
    order, at = room.array(len(names), kind, level), len(names)
    for positions in induce_names(names, smaller, sampled, symbols, room, level):
        order[at - len(positions) : at] = positions[::-1]
        at -= len(positions)
    room.give_back(smaller, sampled)
    return order


def _double(names: np.ndarray) -> np.ndarray:
    rank, size, n = names.astype(np.int64), 1, len(names)
    while True:
        key = rank * (n + 1)
        key[:-size] += rank[size:] + 1
        order = np.argsort(key, kind="stable")
        in_order = key[order]
        rank = np.empty(n, dtype=np.int64)
        rank[order] = np.concatenate([[0], np.cumsum(in_order[1:] != in_order[:-1])])
        size *= 2
        if size >= n or rank[order[-1]] == n - 1:
            return order


def suffixes(text: np.ndarray, cap: int, symbols: int, room: Room) -> Iterator[tuple[np.ndarray, np.ndarray]]:
    """All suffixes, the largest first: positions, and the prefix (up to cap) that each shares with the one before.

    text: small non-negative integers below `symbols`.
    """
    n = len(text)
    if n == 0:
        return
    kind = np.int32 if n < 2**31 - 1 else np.int64
    smaller = kinds(text, room, 0)
    sampled = _sampled(smaller, kind, room, 0)
    if len(sampled) > 1:
        # Induction from the sampled positions in order of their first symbol sorts the stretches between them.
        start = _by_symbol(text, sampled, symbols, room, 0)
        none = room.array(len(start), np.uint8, 0)
        none[:] = 0
        rough = (p for p, _ in induce(text, smaller, start, none, symbols, 1, room))
        sampled = _sorted_samples(text, sampled, rough, room, 0)
        room.give_back(start, none)
    shared = room.array(len(sampled), np.uint8, 0)
    for a, e in _spans(len(sampled)):
        low = max(a, 1)
        shared[low:e] = shared_prefix(text, sampled[low - 1 : e - 1], sampled[low:e], cap)
    shared[:1] = 0
    yield from induce(text, smaller, sampled, shared, symbols, cap, room)


def suffix_array(text: np.ndarray, cap: int, symbols: int, room: Room | None = None) -> tuple[np.ndarray, np.ndarray]:
    """Positions of all suffixes in order, and shared prefixes (up to cap) of neighbours, as arrays."""
    got = list(suffixes(text, cap, symbols, room or Room()))
    if not got:
        return np.zeros(0, dtype=np.int32), np.zeros(0, dtype=np.uint8)
    shared = np.concatenate([s for _, s in got])[::-1]
    return np.concatenate([p for p, _ in got])[::-1], np.concatenate([[0], shared[:-1]]).astype(np.uint8)


def _equal(text: np.ndarray, a: np.ndarray, b: np.ndarray, length: np.ndarray) -> np.ndarray:
    """Whether stretches of the given lengths, cut at the text's end, are equal."""
    n, out = len(text), np.ones(len(a), dtype=bool)
    active, step = np.arange(len(a)), 0
    while len(active):
        i, j = a[active] + step, b[active] + step
        inside = (i < n) & (j < n)
        same = np.zeros(len(active), dtype=bool)
        same[inside] = text[i[inside]] == text[j[inside]]
        out[active[~same]] = False
        step += 1
        active = active[same & (length[active] > step)]
    return out
