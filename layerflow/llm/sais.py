"""Suffix arrays by induced sorting and permuted common prefixes, whole buckets at a time in numpy.

Suffixes are S (smaller than the next one) or L (larger); an S suffix after an L one is leftmost-smaller.  Substrings
between neighbouring leftmost-smaller suffixes are sorted by inducing, named by rank, and, while names repeat, the
string of names is sorted in turn.  From the sorted leftmost-smaller suffixes the order of all is induced: from the
smallest bucket up each suffix puts the L suffix before it at the front of that one's bucket, then from the largest
down S suffixes are put at the ends.  Buckets whose suffixes are all known act together; where a bucket's are not, those
known already act together, and those they add to their own bucket make the next wave.
"""

from __future__ import annotations

import numpy as np

from layerflow.llm.flat import mix


def classify(t: np.ndarray) -> np.ndarray:
    """True where a suffix is smaller than the next one; the empty suffix at the end is the smallest of all."""
    n = len(t)
    s = np.zeros(n + 1, bool)
    s[n] = True
    if n < 2:
        return s
    up = t[1:] > t[:-1]
    step = up.astype(np.int8) - (t[1:] < t[:-1]).astype(np.int8)
    decides = np.where(step != 0, np.arange(n - 1, dtype=np.int32), np.int32(n - 1))
    decides = np.minimum.accumulate(decides[::-1])[::-1]
    s[: n - 1] = np.concatenate([step, np.array([-1], np.int8)])[decides] > 0
    return s


class _Buckets:
    def __init__(self, t: np.ndarray, symbols: int):
        self.count = np.bincount(t, minlength=symbols)
        self.end = np.cumsum(self.count)
        self.start = self.end - self.count


def _place(sa: np.ndarray, at: np.ndarray, suffixes: np.ndarray, chars: np.ndarray, back: bool, missing: np.ndarray | None = None) -> None:
    """Puts suffixes, in order, at the free front (or end) of their buckets."""
    if len(chars) == 0:
        return
    order = np.argsort(chars, kind="stable")
    c = chars[order].astype(np.int64)
    head = np.flatnonzero(np.concatenate([[True], c[1:] != c[:-1]]))
    size = np.diff(np.concatenate([head, [len(c)]]))
    within = np.arange(len(c)) - np.repeat(head, size)
    if back:
        sa[at[c] - 1 - within] = suffixes[order]
        at[c[head]] -= size
    else:
        sa[at[c] + within] = suffixes[order]
        at[c[head]] += size
    if missing is not None:
        missing[c[head]] -= size


def _until_missing(missing: np.ndarray, c: int, stop: int, step: int) -> int:
    """The first bucket from ``c`` on, in direction ``step``, that still misses suffixes; ``stop`` if none does."""
    span = 16
    while c != stop:
        part = missing[c : min(c + span, stop)] if step > 0 else missing[max(c - span, stop) + 1 : c + 1][::-1]
        found = np.flatnonzero(part)
        if len(found):
            return c + step * int(found[0])
        c += step * len(part)
        span *= 4
    return stop


def induce(t: np.ndarray, s: np.ndarray, lms: np.ndarray, b: _Buckets) -> np.ndarray:
    """All suffixes (but the empty one), induced from the leftmost-smaller ones in the order given.

    Neighbouring buckets that miss nothing any more act together; in a bucket that does, waves of its own follow each
    other.  With many symbols, whose buckets are small, most steps take many buckets.
    """
    n, symbols = len(t), len(b.count)
    sa = np.full(n, -1, np.int32)
    tails, heads = b.end.copy(), b.start.copy()
    inner = lms[lms < n][::-1]
    _place(sa, tails, inner, t[inner], back=True)
    first_small = tails.copy()  # of each bucket, where its leftmost-smaller suffixes begin
    n_small = np.bincount(t[s[:n]], minlength=symbols)

    def left(x: np.ndarray, small: bool) -> tuple[np.ndarray, np.ndarray]:
        x = x[x > 0] - 1
        x = x[s[x] == small]
        return x, t[x]

    def put(x: np.ndarray, small: bool) -> None:
        if len(x) == 1:  # runs of one symbol make waves of one suffix
            i = int(x[0]) - 1
            if i >= 0 and s[i] == small:
                c = t[i]
                if small:
                    tails[c] -= 1
                    sa[tails[c]] = i
                else:
                    sa[heads[c]] = i
                    heads[c] += 1
                missing[c] -= 1
            return
        _place(sa, tails if small else heads, *left(x, small), back=small, missing=missing)

    missing = b.count - n_small
    if n:  # the empty suffix comes first
        put(np.array([n]), False)
    c = 0
    while c < symbols:
        upto = _until_missing(missing, c, symbols, 1)
        if upto > c:
            put(sa[b.start[c] : b.end[upto - 1]], False)
            c = upto
            continue
        lo = b.start[c]
        while lo < heads[c]:
            hi = heads[c]
            put(sa[lo:hi], False)
            lo = hi
        put(sa[first_small[c] : b.end[c]], False)
        c += 1
    tails, missing = b.end.copy(), n_small
    c = symbols - 1
    while c >= 0:
        downto = _until_missing(missing, c, -1, -1)
        if downto < c:
            put(sa[b.start[downto + 1] : b.end[c]][::-1], True)
            c = downto
            continue
        hi = b.end[c]
        while hi > tails[c]:
            lo = tails[c]
            put(sa[lo:hi][::-1], True)
            hi = lo
        put(sa[b.start[c] : heads[c]][::-1], True)
        c -= 1
    return sa


def suffix_array(t: np.ndarray, symbols: int | None = None) -> np.ndarray:
    """Starts of all suffixes of a sequence of small non-negative integers, in order."""
    n = len(t)
    if n == 0:
        return np.zeros(0, np.int64)
    symbols = int(t.max()) + 1 if symbols is None else symbols
    s = classify(t)
    lms = (np.flatnonzero(s[1:] & ~s[:-1]) + 1).astype(np.int32)
    b = _Buckets(t, symbols)
    first = induce(t, s, lms, b)
    is_lms = np.zeros(n + 1, bool)
    is_lms[lms] = True
    order = first[is_lms[first]]  # by leftmost-smaller substring; the empty one is left out
    inner = lms[lms < n]
    if len(inner) > 1:
        # names: equal neighbours in this order have equal lengths and hashes of their substrings
        following = np.concatenate([inner[1:], lms[len(inner) :], [n]])[: len(inner)]
        end = np.zeros(n + 1, np.int32)
        end[inner] = np.minimum(following + 1, n + 1)
        up = np.full(n + 1, 0x9E3779B97F4A7C15, np.uint64)
        up[0] = 1
        up = np.cumprod(up, dtype=np.uint64)
        down = np.full(n + 1, pow(0x9E3779B97F4A7C15, -1, 1 << 64), np.uint64)
        down[0] = 1
        down = np.cumprod(down, dtype=np.uint64)
        units = np.concatenate([t.astype(np.uint64) + np.uint64(2), [np.uint64(1)]])
        sums = np.concatenate([np.zeros(1, np.uint64), np.cumsum(units * up, dtype=np.uint64)])
        hashes = mix((sums[end[order]] - sums[order]) * down[order])
        del up, down, units, sums
        size = end[order] - order
        new = np.concatenate([[True], (hashes[1:] != hashes[:-1]) | (size[1:] != size[:-1])])
        name = np.zeros(n + 1, np.int32)
        name[order] = np.cumsum(new) - 1
        order = inner[suffix_array(name[inner], int(new.sum()))] if not new.all() else order
    return induce(t, s, order, b)


def permuted_prefixes(t: np.ndarray, sa: np.ndarray) -> tuple[np.ndarray, np.ndarray]:
    """(PLCP, phi): of each suffix its common prefix with the one before it in the array, and that one (-1: none).

    A suffix whose left neighbours agree has one less than its own left neighbour; only the others are compared.
    """
    n = len(t)
    phi = np.full(n, -1, np.int32)
    phi[sa[1:]] = sa[:-1]
    before, other = t[:-1], phi[1:]
    follows = np.zeros(n, bool)
    if n > 1:
        follows[1:] = (other > 0) & (before == t[np.maximum(other - 1, 0)]) & (phi[:-1] >= 0)
    lead = np.flatnonzero(~follows).astype(np.int32)
    length = np.zeros(len(lead), np.int32)
    padded = np.concatenate([t.astype(np.int16 if t.max(initial=0) < 2**15 else np.int64), np.full(8, -1, np.int16)])
    active = np.flatnonzero(phi[lead] >= 0)
    i, j = lead[active], phi[lead[active]]
    while len(active):
        room = np.minimum(n - i, n - j)
        ok = (room > 0) & (padded[np.minimum(i, n)] == padded[np.minimum(j, n)])
        active, i, j = active[ok], i[ok] + 1, j[ok] + 1
        length[active] += 1
        # longer steps while many units agree
        while len(active):
            step = _agree(padded, i, j, n)
            full = step == 8
            length[active] += step
            i, j = i + step, j + step
            active, i, j = active[full], i[full], j[full]
    owner = np.maximum.accumulate(np.where(follows, np.int32(0), np.arange(n, dtype=np.int32)))
    value = np.zeros(n, np.int32)
    value[lead] = length
    plcp = value[owner] - (np.arange(n, dtype=np.int32) - owner)
    return np.maximum(plcp, 0), phi


def _agree(padded: np.ndarray, i: np.ndarray, j: np.ndarray, n: int) -> np.ndarray:
    """How many of the next eight units agree."""
    out = np.zeros(len(i), np.int32)
    going = np.ones(len(i), bool)
    for k in range(8):
        a, b = np.minimum(i + k, n), np.minimum(j + k, n)
        going &= (i + k < n) & (j + k < n) & (padded[a] == padded[b])
        out += going
    return out
