"""Column-wise construction of the Burrows-Wheeler transform and common prefixes of a string collection.

All strings grow together from their right ends: round j inserts one symbol per string, that is the suffix of
length j.  A suffix is a symbol put before the suffix inserted for the same string a round earlier, so its place
follows from the symbols before that one in the transform, and its common prefix with a neighbour is
one more than the least common prefix between their predecessors.

Transform and common prefixes are files.  A round reads both front to back, merges the new suffixes in and
writes both anew; each block that is written is scanned at once for the places of the next round.  Memory holds one block,
and a few numbers per string, however large the collection is.
"""

from __future__ import annotations

from collections.abc import Iterator
from pathlib import Path

import numpy as np

#: Suffixes that are read, merged and written together.
BLOCK = 1 << 17
#: Above every common prefix.
_NONE = np.uint8(255)


class Files:
    """The transform and the common prefixes, one byte a suffix each, on disk."""

    def __init__(self, folder: Path, name: int):
        self.symbols, self.prefixes, self.size = open(folder / f"symbols.{name}", "w+b"), open(folder / f"prefixes.{name}", "w+b"), 0

    def read(self, block: int = BLOCK) -> Iterator[tuple[np.ndarray, np.ndarray]]:
        self.symbols.seek(0), self.prefixes.seek(0)
        for a in range(0, self.size, block):
            n = min(block, self.size - a)
            yield np.frombuffer(self.symbols.read(n), np.uint8), np.frombuffer(self.prefixes.read(n), np.uint8)

    def write(self, blocks: Iterator[tuple[np.ndarray, np.ndarray]]) -> Iterator[tuple[np.ndarray, np.ndarray]]:
        """Write the blocks over what was there, and hand them on."""
        self.symbols.seek(0), self.prefixes.seek(0)
        self.size = 0
        for bwt, lcp in blocks:
            self.symbols.write(bwt), self.prefixes.write(lcp)
            self.size += len(bwt)
            yield bwt, lcp

    def close(self) -> None:
        self.symbols.close(), self.prefixes.close()


#: All symbols.
_SYMBOLS = np.arange(256, dtype=np.uint8)


class Ranks:
    """Places of a block by symbol, those of one symbol ascending."""

    def __init__(self, bwt: np.ndarray):
        self.order = np.argsort(bwt, kind="stable")
        #: by symbol, where its places end in the order, how many there are, and where they begin
        self.stop = np.searchsorted(bwt, _SYMBOLS, side="right", sorter=self.order)
        self.count = np.diff(self.stop, prepend=0)
        self.begin = self.stop - self.count
        #: symbols that occur
        self.here = np.flatnonzero(self.count)


def _least_before(values: np.ndarray, stops: np.ndarray) -> np.ndarray:
    """The least of values[:stop] for each stop, for few stops."""
    order = np.argsort(stops)
    edges = np.concatenate(([0], stops[order]))
    parts = np.minimum.reduceat(np.append(values[: edges[-1]], _NONE), edges[:-1])
    parts[edges[:-1] == edges[1:]] = _NONE
    out = np.empty(len(stops), dtype=np.uint8)
    out[order] = np.minimum.accumulate(parts)
    return out


def _least_after(values: np.ndarray, starts: np.ndarray) -> np.ndarray:
    """The least of values[start:] for each start, for few starts, all different."""
    order = np.argsort(starts)
    parts = np.minimum.reduceat(np.append(values, _NONE), starts[order])
    out = np.empty(len(starts), dtype=np.uint8)
    out[order] = np.minimum.accumulate(parts[::-1])[::-1]
    return out


def _scan(blocks: Iterator[tuple[np.ndarray, np.ndarray]], at: np.ndarray, base: np.ndarray) -> tuple[np.ndarray, ...]:
    """Where the suffixes of the next round go, from one reading of the files.

    ``at``: ascending places of the suffixes that grow; ``base``: by symbol, the place of its first suffix.
    Returns place, common prefix and the number in ``at`` (-1: an old suffix right after a new one), by place.
    """
    following = base.copy()  # by symbol, the place of its next occurrence
    reach = np.full(256, _NONE)  # least common prefix since the last occurrence
    awaited = np.zeros(256, dtype=bool)  # the last occurrence grows, so the next one has a new neighbour
    found: list[tuple[np.ndarray, ...]] = []
    start = first = 0
    for bwt, lcp in blocks:
        last = int(np.searchsorted(at, start + len(bwt)))
        own = at[first:last] - start
        ranks = Ranks(bwt)
        order, here = ranks.order, ranks.here
        begin, tail = ranks.begin[here], ranks.stop[here] - 1
        grows = np.zeros(len(bwt), dtype=bool)
        grows[own] = True
        grows = grows[order]
        # touched if they grow, or if the occurrence before grows
        touched = grows.copy()
        touched[1:] |= grows[:-1]
        touched[begin] = grows[begin] | awaited[here]
        slot = np.flatnonzero(touched)
        to = order[slot]
        symbol, prefix = bwt[to], lcp[to]
        # they reach back to the occurrence before, or to earlier blocks
        low = order[slot - 1] + 1
        lead = np.flatnonzero(touched[begin])
        lead_at, lead_symbol = np.searchsorted(slot, begin[lead]), here[lead]
        low[lead_at] = to[lead_at]
        far = np.flatnonzero(low != to)
        if len(far):
            by = far[np.argsort(low[far])[::-1]]  # descending, so that nothing between two of them is read
            cuts = np.empty(2 * len(by), dtype=np.int64)
            cuts[::2], cuts[1::2] = low[by], to[by]
            prefix[by] = np.minimum(prefix[by], np.minimum.reduceat(lcp, cuts)[::2])
        if len(lead):
            prefix[lead_at] = np.minimum(np.minimum(prefix[lead_at], _least_before(lcp, to[lead_at])), reach[lead_symbol])
        prefix += np.uint8(1)
        prefix[lead_at[following[lead_symbol] == base[lead_symbol]]] = 0
        number = np.empty(len(bwt), dtype=np.int32)  # read where set only
        number[own] = np.arange(first, last, dtype=np.int32)
        found.append((symbol, slot + (following - ranks.begin)[symbol], prefix, np.where(grows[slot], number[to], np.int32(-1))))
        reach = np.minimum(reach, lcp.min())
        reach[here] = _least_after(lcp, order[tail] + 1)
        awaited[here] = grows[tail]
        following += ranks.count
        start, first = start + len(bwt), last
    symbol, place, prefix, number = (np.concatenate(x) for x in zip(*found, strict=True))
    order = np.argsort(symbol, kind="stable")  # within a symbol places ascend already
    return place[order], prefix[order], number[order]


def _merge(blocks: Iterator[tuple[np.ndarray, np.ndarray]], size: int, place: np.ndarray, prefix: np.ndarray, fresh: np.ndarray, symbols: np.ndarray) -> Iterator[tuple[np.ndarray, np.ndarray]]:
    """The files with the new suffixes put in; ``size``: how many there were."""
    into = place[fresh]
    before = into - np.arange(len(into))  # old suffixes before each new one
    start, put, told = 0, 0, 0
    for bwt, lcp in blocks:
        stop = start + len(bwt)
        upto = len(into) if stop == size else int(np.searchsorted(before, stop))
        first, more = start + put, upto - put
        new_bwt, new_lcp = np.empty(len(bwt) + more, dtype=np.uint8), np.empty(len(bwt) + more, dtype=np.uint8)
        old = np.ones(len(new_bwt), dtype=bool)
        own = into[put:upto] - first
        old[own] = False
        new_bwt[old], new_lcp[old] = bwt, lcp
        new_bwt[own] = symbols[put:upto]
        to = int(np.searchsorted(place, first + len(new_bwt)))
        new_lcp[place[told:to] - first] = prefix[told:to]
        yield new_bwt, new_lcp
        start, put, told = stop, upto, to


def build(data: np.ndarray, starts: np.ndarray, lengths: np.ndarray, folder: Path, block: int = BLOCK) -> Files:
    """Files of the strings data[starts : starts + lengths], of 1 to 254 bytes each and of at most 255 different bytes.

    Symbols are byte ranks from 1, 0 marks a string's start.  The common prefix at p is that of the suffixes
    at p - 1 and p.  The first suffixes are the empty ones, in the order of the strings.
    """
    n = len(starts)
    used = np.zeros(256, dtype=bool)
    used[data] = True
    text = np.cumsum(used).astype(np.uint8)[data]
    ends = starts + lengths
    at, who = np.arange(n), np.arange(n)  # place and string of the suffixes that grow
    fresh, place, prefix = np.ones(n, dtype=bool), at, np.zeros(n, dtype=np.uint8)
    symbols = text[ends - 1]
    counts = np.bincount(symbols, minlength=256)
    files, other, size = Files(folder, 0), Files(folder, 1), 0
    for j in range(1, int(lengths.max(initial=0)) + 2):
        old = files.read(block) if size else iter([(symbols[:0], symbols[:0])])
        files, other = other, files
        rewritten = files.write(_merge(old, size, place, prefix, fresh, symbols))
        size += len(symbols)
        if not len(at):
            for _ in rewritten:
                pass
            break
        proper = np.where(np.arange(256) > 0, counts, 0)
        place, prefix, number = _scan(rewritten, at, n + np.cumsum(proper) - proper)
        fresh = number >= 0
        strings = who[number[fresh]]
        left = lengths[strings] > j
        symbols = np.zeros(len(strings), dtype=np.uint8)
        symbols[left] = text[ends[strings[left]] - 1 - j]
        counts = counts + np.bincount(symbols, minlength=256)
        at, who = place[fresh][left], strings[left]
    other.close()
    return files


def windows_at(files: Files, n: int, lengths: np.ndarray, span: int) -> tuple[np.ndarray, np.ndarray]:
    """(place of every window of ``span`` symbols, string after string; group of every place).

    Suffixes of one group are neighbours with common prefixes of at least the span.  The places follow from
    a walk along the transform from the empty suffixes; it takes four bytes a suffix.
    """
    counts = np.zeros(256, dtype=np.int64)
    for bwt, _ in files.read():
        counts += np.bincount(bwt, minlength=256)
    counts[0] = 0
    to, group = np.full(files.size, -1, dtype=np.int32), np.empty(files.size, dtype=np.int32)
    following, start, groups = n + np.cumsum(counts) - counts, 0, 0
    for bwt, lcp in files.read():
        ranks, stop = Ranks(bwt), start + len(bwt)
        to[start + ranks.order] = np.arange(len(bwt)) + np.repeat(following - ranks.begin, ranks.count)
        to[start + ranks.order[: ranks.count[0]]] = -1
        following += ranks.count
        group[start:stop] = groups + np.cumsum(lcp < span)
        start, groups = stop, int(group[stop - 1])
    windows = np.maximum(lengths - span + 1, 0)
    end = np.cumsum(windows)
    where = np.empty(int(windows.sum()), dtype=np.int32)
    at, who, length = np.arange(n), np.arange(n), 0
    while len(at):
        if length >= span:
            where[end[who] - 1 - (length - span)] = at
        at = to[at]
        alive = at >= 0
        at, who, length = at[alive], who[alive], length + 1
    return where, group


def shared_least(data: np.ndarray, starts: np.ndarray, lengths: np.ndarray, owner: np.ndarray, span: int, folder: Path, block: int = BLOCK) -> np.ndarray:
    """For every run of ``span`` bytes, string after string: the least ``owner`` of a string that holds the same run."""
    windows = np.maximum(lengths - span + 1, 0)
    if not windows.any():
        return owner[:0]
    files = build(data, starts, lengths, folder, block)
    where, group = windows_at(files, len(starts), lengths, span)
    files.close()
    own = group[where]
    least = np.full(int(own.max()) + 1, np.iinfo(owner.dtype).max, dtype=owner.dtype)
    np.minimum.at(least, own, np.repeat(owner, windows))
    return least[own]
