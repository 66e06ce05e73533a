"""Signature trees over token sets: who in a group can still be similar.

A leaf holds up to ``LEAF`` sets with their bitmaps (a bit for each token's hash) and sizes; an inner node holds the
OR of its children's bitmaps, the range of their sizes, and their component if they all have one.  A dual traversal
starts at (root, root) and drops a pair of nodes if their size ranges can't meet the threshold, if the largest overlap
their bitmaps allow is too small, or if both are wholly of one component.  Leaf pairs are compared set by set with the
same bound: tokens of x whose bit y lacks are not in y, so at most ``|x| - bits(x & ~y)`` are shared.
"""

from __future__ import annotations

import numpy as np

LEAF = 32
FAN_OUT = 8
#: Open pairs after which a search for the likeliest ones drops the others.
FEW = 200_000


def possible(small: np.ndarray, missing_x: np.ndarray, nx: np.ndarray, missing_y: np.ndarray, ny: np.ndarray, percent: int) -> np.ndarray:
    """Whether an overlap bounded by the missing bits can reach percent/100 of the union."""
    most = np.minimum(np.minimum(nx - missing_x, ny - missing_y), small)
    return 100 * most >= percent * (nx + ny - most)


def pair_bound(bits_x: np.ndarray, nx: np.ndarray, bits_y: np.ndarray, ny: np.ndarray, percent: int) -> np.ndarray:
    """Rowwise: can these two sets be similar?"""
    mx = np.bitwise_count(bits_x & ~bits_y).sum(axis=-1, dtype=np.int64)
    my = np.bitwise_count(bits_y & ~bits_x).sum(axis=-1, dtype=np.int64)
    return possible(np.minimum(nx, ny), mx, nx, my, ny, percent)


def fold(bits: np.ndarray, words: int) -> np.ndarray:
    """Bitmaps of 64-bit words, halved by OR until they have so many: as if their tokens had been hashed to fewer bits."""
    while bits.shape[1] > words:
        half = bits.shape[1] // 2
        bits = bits[:, :half] | bits[:, half:]
    return bits


def pairs_of_any_width(bits: list[bytes], size: np.ndarray, component: np.ndarray, side: np.ndarray | None, percent: int, nearest: int | None = None) -> np.ndarray:
    """``similar_pairs`` of members with bitmaps of several widths, which follow their sizes.

    Similar sets have widths at most a step of two apart, so each width is searched by itself and against the next.
    """
    words = np.array([len(b) // 8 for b in bits])
    found = [np.zeros((0, 3), np.int32)]
    for w in np.unique(words).tolist():
        for wide in (w, 2 * w):
            at = np.flatnonzero((words == w) | (words == wide))
            if len(at) < 2 or (wide > w and not (words[at] == wide).any()):
                continue
            rows = np.empty((len(at), w), np.uint64)
            for width in {w, wide}:
                own = np.flatnonzero(words[at] == width)
                rows[own] = fold(np.frombuffer(b"".join(bits[i] for i in at[own].tolist()), np.uint64).reshape(-1, width), w)
            by = None if side is None else side[at]
            if wide > w:
                pairs = similar_pairs(rows, size[at], component[at], words[at], percent, None if by is not None else nearest)
                if by is not None:
                    pairs = pairs[by[pairs[:, 0]] != by[pairs[:, 1]]]
            else:
                pairs = similar_pairs(rows, size[at], component[at], by, percent, nearest)
            found.append(np.column_stack([at[pairs[:, :2]], pairs[:, 2]]).astype(np.int32))
    return np.concatenate(found)


def nearest_of_components(pairs: np.ndarray, component: np.ndarray, keep: int) -> np.ndarray:
    """Of the pairs between each two components the ``keep`` whose bitmaps differ least."""
    a, b = component[pairs[:, 0]], component[pairs[:, 1]]
    low, high = np.minimum(a, b), np.maximum(a, b)
    order = np.lexsort((pairs[:, 2], high, low))
    first = np.concatenate([[True], (low[order][1:] != low[order][:-1]) | (high[order][1:] != high[order][:-1])])[: len(order)]
    begin = np.maximum.accumulate(np.where(first, np.arange(len(order)), 0))
    return pairs[order[np.arange(len(order)) - begin < keep]]


class Tree:
    def __init__(self, bits: np.ndarray, size: np.ndarray, component: np.ndarray, order: np.ndarray):
        """order: members, like ones near each other."""
        self.bits, self.size, self.component, self.members = bits, size, component, order
        cut = list(range(0, len(order), LEAF))
        self.levels = [[(a, min(a + LEAF, len(order))) for a in cut]]
        self.nodes = [self._sum_up([order[a:b] for a, b in self.levels[0]])]
        while len(self.levels[-1]) > 1:
            below = len(self.levels[-1])
            self.levels.append([(a, min(a + FAN_OUT, below)) for a in range(0, below, FAN_OUT)])
            bits, low, high, comp, least = self.nodes[-1]
            spans = self.levels[-1]
            self.nodes.append((
                np.array([np.bitwise_or.reduce(bits[a:b]) for a, b in spans]), np.array([low[a:b].min() for a, b in spans]), np.array([high[a:b].max() for a, b in spans]),
                np.array([comp[a] if (comp[a:b] == comp[a]).all() else -1 for a, b in spans]), np.array([least[a:b].min() for a, b in spans]),
            ))

    def _sum_up(self, groups: list[np.ndarray]):
        """OR of bitmaps, sizes from and to, the one component or -1, and the fewest bits of a member."""
        bits = np.array([np.bitwise_or.reduce(self.bits[g]) for g in groups])
        low, high = np.array([self.size[g].min() for g in groups]), np.array([self.size[g].max() for g in groups])
        comp = np.array([self.component[g[0]] if (self.component[g] == self.component[g[0]]).all() else -1 for g in groups])
        return bits, low, high, comp, np.array([np.bitwise_count(self.bits[g]).sum(axis=1).min() for g in groups])


def _open_pairs(x: tuple, y: tuple, i: np.ndarray, j: np.ndarray, percent: int) -> np.ndarray:
    """Which pairs of nodes may hold a similar pair of sets of different components."""
    bx, lx, hx, cx, px = (a[i] for a in x)
    by, ly, hy, cy, py = (a[j] for a in y)
    sizes = (100 * hx >= percent * ly) & (100 * hy >= percent * lx)
    # a member of x has at least px bits; those beyond the bits common with all of y are tokens no member of y has
    both = np.bitwise_count(bx & by).sum(axis=1, dtype=np.int64)
    most = np.minimum(np.minimum(hx - np.maximum(px - both, 0), hy - np.maximum(py - both, 0)), np.minimum(hx, hy))
    overlap = 100 * most >= percent * (np.maximum(lx, most) + np.maximum(ly, most) - most)
    return sizes & overlap & ((cx != cy) | (cx == -1))


def similar_pairs(bits: np.ndarray, size: np.ndarray, component: np.ndarray, side: np.ndarray | None, percent: int, nearest: int | None = None) -> np.ndarray:
    """Pairs of members that the bounds leave open, with the number of bits in which they differ; ``side``: only pairs of different sides."""
    n = len(size)
    order = np.lexsort((bits[:, 0], component, size))
    tree = Tree(bits, size, component, order)
    top = len(tree.levels) - 1
    i, j = np.array([0]), np.array([0])
    for level in range(top, 0, -1):
        x = tree.nodes[level]
        ok = _open_pairs(x, x, i, j, percent)
        spans = np.array(tree.levels[level])
        out = []
        for a, b in zip(i[ok].tolist(), j[ok].tolist()):
            p, q = np.arange(*spans[a]), np.arange(*spans[b])
            g = np.stack(np.meshgrid(p, q, indexing="ij"), -1).reshape(-1, 2)
            out.append(g[g[:, 0] <= g[:, 1]] if a == b else g)
        if not out:
            return np.zeros((0, 3), np.int64)
        i, j = np.concatenate(out).T
    ok = _open_pairs(tree.nodes[0], tree.nodes[0], i, j, percent)
    spans, found, held = tree.levels[0], [], 0
    for a, b in zip(i[ok].tolist(), j[ok].tolist()):
        p, q = order[slice(*spans[a])], order[slice(*spans[b])]
        u, v = np.repeat(p, len(q)), np.tile(q, len(p))
        if a == b:
            keep = np.repeat(np.arange(len(p)), len(q)) < np.tile(np.arange(len(q)), len(p))
            u, v = u[keep], v[keep]
        keep = (component[u] != component[v]) & (100 * np.minimum(size[u], size[v]) >= percent * np.maximum(size[u], size[v]))
        if side is not None:
            keep &= side[u] != side[v]
        u, v = u[keep], v[keep]
        if len(u):
            keep = pair_bound(bits[u], size[u], bits[v], size[v], percent)
            if keep.any():
                u, v = u[keep], v[keep]
                found.append(np.stack([u, v, np.bitwise_count(bits[u] ^ bits[v]).sum(axis=1, dtype=np.int64)], 1).astype(np.int32))
                held += len(u)
                if nearest and held > FEW:
                    found = [nearest_of_components(np.concatenate(found), component, nearest)]
                    held = 0
    return np.concatenate(found) if found else np.zeros((0, 3), np.int64)
