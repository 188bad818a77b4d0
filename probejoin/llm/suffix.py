"""Suffix arrays by induced sorting, and common prefixes in text order.

A suffix is small if it comes before the one that follows it in the text, else large. The
leftmost of each run of small suffixes are sorted first: one round of inducing puts the
substrings between them in order, equal ones get one name, and the order of the suffixes of
the string of names, at most half as long and sorted by the same procedure, is theirs. A
second round induces all the other suffixes from them.

A round of inducing goes through the text's letters in order (few letters, as in bytes): all
suffixes of a letter that are ready are taken together, their predecessors dealt out stably
to the letters they begin with, and those that stay with the letter form the next wave; it
touches each place once. Strings of names have nearly as many letters as places; there a
suffix's rank follows from its letter and the rank of the suffix after it, and runs of such
steps are halved until each ends at a suffix that is known. That takes as many sorts as the
longest run has binary digits, each of those places only that are not yet told apart.

Common prefixes are found in text order: where a suffix and its neighbour in the order are
preceded by the same letter, the value is that of the place before less one. Only the other
places are compared, eight bytes at a time.
"""

from __future__ import annotations

import numpy as np

#: Letters up to which a round goes letter by letter, and places there must be for each.
FEW, LEAST_EACH = 1024, 32


def small_suffixes(t: np.ndarray) -> np.ndarray:
    """True where a suffix is smaller than the one after it; the last letter is a sentinel."""
    n = len(t)
    step = np.sign(np.diff(t.astype(np.int64)))
    place = np.where(step != 0, np.arange(n - 1), n)
    following = np.minimum.accumulate(place[::-1])[::-1]
    out = np.ones(n, np.bool_)
    if n > 1:
        out[:-1] = step[np.minimum(following, n - 2)] > 0
    return out


class _Dealt:
    """Lists of arrays by letter."""

    def __init__(self, letters: int):
        self.held: list[list[np.ndarray]] = [[] for _ in range(letters)]

    def deal(self, places: np.ndarray, letters: np.ndarray) -> None:
        if not len(places):
            return
        order = np.argsort(letters, kind="stable")
        places, letters = places[order], letters[order]
        cut = np.flatnonzero(np.diff(letters)) + 1
        start = 0
        for end in (*cut.tolist(), len(places)):
            self.held[letters[start]].append(places[start:end])
            start = end

    def take(self, letter: int) -> np.ndarray | None:
        got = self.held[letter]
        return None if not got else got[0] if len(got) == 1 else np.concatenate(got)


def by_letters(t: np.ndarray, small: np.ndarray, seeds: np.ndarray, letters: int) -> np.ndarray:
    """All places in the order that the leftmost small suffixes, in the order given, induce."""
    own = _Dealt(letters)
    own.deal(seeds, t[seeds])
    large, smaller = _Dealt(letters), _Dealt(letters)
    done: list[list[np.ndarray]] = [[] for _ in range(letters)]
    for c in range(letters):
        wave = large.take(c)
        while wave is not None and len(wave):
            done[c].append(wave)
            before = wave[wave > 0] - 1
            before = before[~small[before]]
            first = t[before]
            same = first == c
            large.deal(before[~same], first[~same])
            wave = before[same]
        seed = own.take(c)
        if seed is not None:
            before = seed[seed > 0] - 1
            before = before[~small[before]]
            large.deal(before, t[before])
    out: list[np.ndarray] = []
    for c in range(letters - 1, -1, -1):
        wave = smaller.take(c)
        if c == 0:
            wave = np.array([len(t) - 1])
        while wave is not None and len(wave):
            out.append(wave)
            before = wave[wave > 0] - 1
            before = before[small[before]]
            first = t[before]
            same = first == c
            smaller.deal(before[~same], first[~same])
            wave = before[same]
        for part in reversed(done[c]):
            part = part[::-1]
            out.append(part)
            before = part[part > 0] - 1
            before = before[small[before]]
            smaller.deal(before, t[before])
    return np.concatenate(out)[::-1]


#: Letters up to which pairs of substrings are compared together; longer ones are few.
TOGETHER = 48


def differs(t: np.ndarray, found: np.ndarray, size: np.ndarray) -> np.ndarray:
    """Whether each substring, given in order by place and length, differs from the one before it."""
    a, b = found[:-1], found[1:]
    out = size[:-1] != size[1:]
    live = np.flatnonzero(~out)
    for k in range(TOGETHER):
        live = live[size[live] > k]
        if not len(live):
            return out
        other = t[a[live] + k] != t[b[live] + k]
        out[live[other]] = True
        live = live[~other]
    for i in live[size[live] > TOGETHER].tolist():
        x, y, n = int(a[i]), int(b[i]), int(size[i])
        out[i] = not np.array_equal(t[x + TOGETHER : x + n], t[y + TOGETHER : y + n])
    return out


def dense(key: np.ndarray) -> np.ndarray:
    """Rank of each value among the distinct ones."""
    order = np.argsort(key)
    own = key[order]
    out = np.empty(len(key), np.int64)
    out[order] = np.concatenate(([0], np.cumsum(own[1:] != own[:-1])))
    return out


def chained(key: np.ndarray, hop: np.ndarray) -> np.ndarray:
    """Ranks of the sequences of keys met from each node on; a sequence ends at a node that hops to itself.

    Nodes hop to different nodes unless these are ends, and an end's key is no other node's. Equal
    sequences have equal ranks. Only nodes that share a rank are sorted again.
    """
    n = len(key)
    order = np.argsort(key)
    own = key[order]
    new = np.concatenate(([True], own[1:] != own[:-1]))
    rank, hop = np.empty(n, np.int64), hop.copy()
    rank[order] = np.maximum.accumulate(np.where(new, np.arange(n), 0))
    left = order[~new | np.append(~new[1:], False)]
    left = left[hop[left] != left]
    while len(left):
        group, to = rank[left], hop[left]
        pair = group * np.int64(n) + rank[to]
        order = np.argsort(pair)
        left, group, to, pair = left[order], group[order], to[order], pair[order]
        at = np.arange(len(left))
        new = np.concatenate(([True], pair[1:] != pair[:-1]))
        begins = np.concatenate(([True], group[1:] != group[:-1]))
        rank[left] = group + np.maximum.accumulate(np.where(new, at, 0)) - np.maximum.accumulate(np.where(begins, at, 0))
        on = (~new | np.append(~new[1:], False)) & (hop[to] != to)
        left = left[on]
        hop[left] = hop[to[on]]
    return rank


def by_chains(t: np.ndarray, small: np.ndarray, first: np.ndarray) -> np.ndarray:
    """Rank of every suffix from those of the leftmost small ones in first (-1 elsewhere); equal ranks stay equal."""
    n, place = len(t), np.arange(len(t))
    leftmost = first >= 0
    nodes = np.flatnonzero(~small | leftmost)
    at = np.cumsum(~small | leftmost) - 1
    own = leftmost[nodes]
    key = (2 * t[nodes] + own) * np.int64(n + 1) + np.where(own, first[nodes], 0)
    large = np.zeros(n, np.int64)
    large[nodes] = chained(key, np.where(own, np.arange(len(nodes)), at[np.minimum(nodes + 1, n - 1)]))
    key = (2 * t + small) * np.int64(n + 1) + np.where(small, 0, large)
    hop = np.where(small, np.minimum(place + 1, n - 1), place)
    return chained(key, hop)


def _sorted_with_sentinel(t: np.ndarray) -> np.ndarray:
    """Places in suffix order of letters that end in the only 0."""
    n = len(t)
    if n < 3:
        return np.arange(n - 1, -1, -1)
    small = small_suffixes(t)
    seeds = np.flatnonzero(small[1:] & ~small[:-1]) + 1
    letters = int(t.max()) + 1
    few = letters <= FEW and letters * LEAST_EACH <= n
    name = np.full(n, -1, np.int64)
    if few:
        leftmost = np.zeros(n, np.bool_)
        leftmost[seeds] = True
        found = by_letters(t, small, seeds, letters)
        found = found[leftmost[found]]
        size = np.empty(n, np.int64)
        size[seeds] = np.append(np.diff(seeds) + 1, 1)
        name[found] = np.concatenate(([0], np.cumsum(differs(t, found, size[found]))))
    else:
        name[seeds] = 0
        name[seeds] = dense(by_chains(t, small, name)[seeds])
    names = name[seeds]
    found = np.argsort(names) if int(names.max()) == len(seeds) - 1 else _sorted_with_sentinel(names)
    if few:
        return by_letters(t, small, seeds[found], letters)
    name[seeds[found]] = np.arange(len(seeds))
    return np.argsort(by_chains(t, small, name))


def suffix_array(letters: np.ndarray) -> np.ndarray:
    """Places of all suffixes of a string of small integers from 0 in order."""
    t = np.zeros(len(letters) + 1, np.int64 if len(letters) and letters.max() >= FEW else np.int16)
    t[:-1] = letters
    t[:-1] += 1
    return _sorted_with_sentinel(t)[1:]


def common_prefixes(letters: np.ndarray, order: np.ndarray, room: np.ndarray) -> np.ndarray:
    """For each place, in text order, how far its suffix agrees with the one before it in order, up to room letters.

    room falls by one from place to place but where it is 0, as behind the last letter of a string.
    """
    n = len(letters)
    other = np.full(n, -1, np.int64)
    other[order[1:]] = order[:-1]
    at = np.arange(n)
    same = (other > 0) & (at > 0)
    same[same] = letters[at[same] - 1] == letters[other[same] - 1]
    same[1:] &= room[:-1] > 0  # the first place of a string is compared
    out = np.zeros(n, np.int64)
    live = np.flatnonzero(~same & (other >= 0) & (room > 0))
    if letters.dtype == np.uint8:
        padded = np.concatenate((letters, np.zeros(8, np.uint8)))
        eight = np.ndarray((n + 1,), np.uint64, buffer=padded.data, strides=(1,))
    else:
        eight = None
    x, y, done = live, other[live], 0
    while len(live):
        if eight is not None:
            apart = eight[np.minimum(x + done, n)] ^ eight[np.minimum(y + done, n)]
            got = np.bitwise_count((apart & (~apart + np.uint64(1))) - np.uint64(1)).astype(np.int64) >> 3
            step = 8
        else:
            i, k = x + done, y + done
            inside = (i < n) & (k < n)
            got = np.where(inside, letters[np.minimum(i, n - 1)] == letters[np.minimum(k, n - 1)], False).astype(np.int64)
            step = 1
        out[live] = done + got
        on = (got == step) & (room[live] > done + step)
        live, x, y, done = live[on], x[on], y[on], done + step
    out = np.minimum(np.minimum(out, room), np.where(other >= 0, n - other, 0))
    last = np.maximum.accumulate(np.where(same, -1, at))
    return np.where(same, np.maximum(out[last] - (at - last), 0), out)


def repeated_windows(letters: np.ndarray, room: np.ndarray, length: int) -> tuple[np.ndarray, np.ndarray]:
    """Places whose next length letters also follow another place, and the number of their class.

    letters are strings that each end in a letter that none of them holds; room is what is left of
    the own string, 0 at its end. Classes are runs of the suffix array in which the permuted common
    prefixes reach length; nothing but those prefixes decides.
    """
    order = suffix_array(letters)
    reach = common_prefixes(letters, order, room)[order] >= length
    if not len(order) or not reach.any():
        return np.empty(0, np.int64), np.empty(0, np.int64)
    run = np.cumsum(~reach)
    again = reach.copy()
    again[:-1] |= reach[1:]
    return order[again], run[again]
