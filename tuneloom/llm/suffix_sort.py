"""Suffix arrays by induced sorting, and permuted common prefixes, for one shard's bytes.

Suffixes are classified as smaller or larger than their right neighbour; the leftmost-smaller substrings, which are short, are
sorted and named by numbers that hold several symbols; their names are a string that the same function sorts where names
repeat; induction from them gives the whole array. Buckets are
counted ranges of one array at every level, whatever the alphabet: a step of the scan takes a stretch of it inside which
nothing is induced any more, and deals what the stretch induces by a stable sort, which keeps the order of the sequential
scan. So each pass runs in numpy.
"""

from __future__ import annotations

import numpy as np

def _smaller(s: np.ndarray) -> np.ndarray:
    """True for suffixes smaller than the next one; the last symbol is the unique least."""
    n = len(s)
    up = np.empty(n, bool)
    up[-1] = True
    less, equal = s[:-1] < s[1:], s[:-1] == s[1:]
    # equal neighbours take the class of the next unequal place
    nxt = np.where(equal, n - 1, np.arange(n - 1))
    nxt = np.minimum.accumulate(nxt[::-1])[::-1]
    up[:-1] = np.where(nxt < n - 1, less[np.minimum(nxt, n - 2)], True)
    return up


#: Slots of the array that one step of the scan looks at, at least and at most.
CHUNK = (1 << 10, 1 << 18)


def _scan(slots: np.ndarray, s: np.ndarray, picks: np.ndarray, head: np.ndarray) -> None:
    """One pass of induction over the slots of the suffix array (-1: empty), in order.

    Behind each suffix found, the suffix in front of it in the text, if picked, takes the next free slot of its symbol. A step
    takes as many found suffixes as none of them can be preceded by what the others induce: from the first that lies at or
    behind the symbol of an earlier one's result, the scan goes on in the next step. So buckets are counters, an alphabet may
    be as large as the text, and many small buckets go in one step.
    """
    n, i, chunk = len(slots), 0, CHUNK[0]
    never = np.int32(2**31 - 1)
    while i < n:
        stop = min(n, i + chunk)
        filled = np.flatnonzero(slots[i:stop] >= 0)
        if not len(filled):
            i, chunk = stop, min(2 * chunk, CHUNK[1])
            continue
        found = slots[i:stop][filled]
        front = found - 1  # -1 of the first suffix meets the last symbol, which is never picked
        take = picks[front]
        symbol = np.where(take, s[front].astype(np.int32), never)
        least = np.minimum.accumulate(symbol)
        own = s[found]
        late = (least[:-1] < own[1:]) | ((least[:-1] == own[1:]) & ~picks[found[1:]])
        cut = int(late.argmax()) + 1 if late.any() else len(found)
        front, symbol = front[:cut][take[:cut]], symbol[:cut][take[:cut]]
        end = i + int(filled[cut]) if cut < len(found) else stop
        if len(front):
            order = np.argsort(symbol.astype(s.dtype), kind="stable")
            symbol = symbol[order]
            first = np.flatnonzero(np.concatenate([[True], symbol[1:] != symbol[:-1]]))
            size = np.diff(np.append(first, len(symbol)))
            at = np.repeat(head[symbol[first]] - first, size) + np.arange(len(symbol))
            slots[at] = front[order]
            head[symbol[first]] += size
            ahead = at[at >= i]
            end = min(end, int(ahead.min())) if len(ahead) else end
        chunk = min(max(2 * (end - i), CHUNK[0]), CHUNK[1])
        i = end


def _induce(s: np.ndarray, up: np.ndarray, symbols: int, seeds: np.ndarray) -> np.ndarray:
    """All suffixes in order, from the leftmost-smaller ones in order."""
    n = len(s)
    size = np.bincount(s, minlength=symbols)
    after = np.cumsum(size)
    slots = np.full(n, -1, np.int32)
    c = s[seeds]
    order = np.argsort(c, kind="stable")
    many = np.bincount(c, minlength=symbols)
    place = np.arange(len(seeds)) - np.repeat(np.cumsum(many) - many, many) + np.repeat(after - many, many)
    slots[place] = seeds[order]
    down = ~up
    _scan(slots, s, down, after - size)
    slots[place] = -1
    # the mirror image: from the last slot to the first, symbols counted from the largest
    slots[0] = n - 1  # the end mark
    mirror = (symbols - 1 - s.astype(np.int32)).astype(s.dtype)
    _scan(slots[::-1], mirror, up & (np.arange(n) < n - 1), (n - after)[::-1].copy())
    return slots


def _named(s: np.ndarray, symbols: int, lead: np.ndarray) -> np.ndarray:
    """The rank of each leftmost-smaller substring among the distinct ones; lead: where they begin.

    As many symbols as fit in one number are compared at a time; only substrings equal so far go on. One that ends where another
    goes on is the larger: there the other falls.
    """
    n = len(s)
    stop = np.append(lead[1:], n - 1).astype(np.int64)  # the last symbol of each
    bits = int(symbols + 1).bit_length()
    per = 63 // bits
    padded = np.concatenate([s.astype(np.int64), np.zeros(per, np.int64)])
    rank = np.zeros(len(lead), np.int64)
    live, at = np.arange(len(lead)), lead.astype(np.int64)
    while len(live):
        here, last = at[live], stop[live]
        key = np.zeros(len(live), np.int64)
        for d in range(per):
            key = key << bits | np.where(here + d <= last, padded[np.minimum(here + d, n)], symbols)
        # within each group of equal ranks, which count the substrings before it, by the next symbols
        order = np.argsort(key, kind="stable") if len(live) == len(lead) else np.lexsort((key, rank[live]))
        group, key, place = rank[live[order]], key[order], live[order]
        i = np.arange(len(live))
        new_group = np.concatenate([[True], group[1:] != group[:-1]])
        new = new_group | np.concatenate([[True], key[1:] != key[:-1]])
        head = np.maximum.accumulate(np.where(new_group, i, 0))
        first = np.maximum.accumulate(np.where(new, i, 0))
        rank[place] = group + first - head
        # equal substrings of which one goes on are looked at again, all that are equal
        same = np.cumsum(new) - 1
        more = np.bincount(same, weights=at[place] + per <= stop[place]) > 0
        tied = ~(new & np.append(new[1:], True))
        live = place[tied & more[same]]
        at = at + per
    distinct = np.zeros(len(lead), bool)
    distinct[rank] = True
    return (np.cumsum(distinct) - 1)[rank]


def _sorted(s: np.ndarray, symbols: int) -> np.ndarray:
    """Suffix array of a string that ends with its unique least symbol."""
    n = len(s)
    if n == 1:
        return np.zeros(1, np.int32)
    up = _smaller(s)
    is_lead = np.zeros(n, bool)
    is_lead[1:] = up[1:] & ~up[:-1]
    lead = np.flatnonzero(is_lead).astype(np.int32)
    names = _named(s, symbols, lead)  # the last is that of the end mark, unique and least
    many = int(names.max()) + 1
    if many < len(lead):
        order = _sorted(names.astype(np.int16 if many <= 1 << 15 else np.int32), many)
    else:
        order = np.empty(len(lead), np.int64)
        order[names] = np.arange(len(lead))
    return _induce(s, up, symbols, lead[order])


def suffix_array(data: np.ndarray) -> np.ndarray:
    """Suffix array of bytes (the empty suffix left out)."""
    return _sorted(np.append(data.astype(np.int16) + 1, np.int16(0)), 257)[1:]


def common_prefixes(data: np.ndarray, sa: np.ndarray) -> np.ndarray:
    """Length of the common prefix of each suffix, in text order, with its predecessor in the suffix array.

    Where the symbols in front of both are equal the length is one less than that in front; only the other places, whose
    lengths sum to little, are compared.
    """
    n = len(data)
    if not n:
        return np.empty(0, np.int64)
    before = np.empty(n, np.int64)
    before[sa[1:]] = sa[:-1]
    before[sa[0]] = -1
    i = np.arange(n)
    fresh = (i == 0) | (before <= 0)
    inner = ~fresh
    fresh[inner] = data[i[inner] - 1] != data[before[inner] - 1]
    # a place whose front neighbour is first in the array starts anew as well
    fresh[1:] |= before[:-1] < 0
    at = np.flatnonzero(fresh & (before >= 0))
    padded = np.concatenate([data, np.zeros(16, np.uint8)])
    words = np.lib.stride_tricks.as_strided(padded[:8].view(np.uint64), (n + 8,), (1,))
    length = np.zeros(n, np.int64)
    live, d = at, 0
    while len(live):
        a, b = live + d, before[live] + d
        x = words[a] ^ words[b]
        same = np.bitwise_count((x & (~x + np.uint64(1))) - np.uint64(1)).astype(np.int64) >> 3
        same = np.where(x == 0, 8, same)
        same = np.minimum(same, n - np.maximum(a, b))
        length[live] += same
        live = live[(same == 8) & (np.maximum(a, b) + 8 < n)]
        d += 8
    source = np.maximum.accumulate(np.where(fresh, i, 0))
    return np.maximum(length[source] - (i - source), 0)
