"""Joins of tries over fingerprints of many words, under a Hamming budget."""

from __future__ import annotations

import math

import numpy as np

from entlink.llm.unions import Classes

FRONTIER = 1 << 13
ADDED_AT_ONCE = 192  # rows whose bits are counted by unpacking
HELD_DEPTHS = 48
FEW = 16  # pairs of leaves below two nodes that are compared without walking on


def _bit_sums(rows: np.ndarray) -> np.ndarray:
    return np.unpackbits(rows.astype(">u8").view(np.uint8).reshape(len(rows), -1), axis=1).sum(axis=0, dtype=np.int64)


def bit_counts(rows: np.ndarray) -> np.ndarray:
    """How many rows of 64-bit words have each bit, highest first.

    Many rows are added as bit planes: three rows of one weight become one of that weight and one of twice the weight.
    """
    sums, weight = np.zeros(64 * rows.shape[1], np.int64), 1
    while len(rows) > ADDED_AT_ONCE:
        carried = []
        while len(rows) >= 3:
            m = len(rows) // 3
            a, b, c = rows[:m], rows[m : 2 * m], rows[2 * m : 3 * m]
            x = a ^ b
            carried.append((a & b) | (x & c))
            rows = np.concatenate((x ^ c, rows[3 * m :]))
        sums += weight * _bit_sums(rows)
        rows, weight = np.concatenate(carried), 2 * weight
    return sums + weight * _bit_sums(rows)


def permutation(size: int, seed: int) -> np.ndarray:
    """An order of the bits, the same everywhere."""
    return np.random.Generator(np.random.PCG64(seed)).permutation(size)


def prefixes(flat: np.ndarray, order: np.ndarray, bits: int) -> np.ndarray:
    """The first ``bits`` (64 at most) of each row of bits in an order."""
    packed = np.ascontiguousarray(np.packbits(flat[:, order[:64]], axis=1))
    return packed.view(">u8").ravel().astype(np.uint64) >> np.uint64(64 - bits)


def tries_for(n: int, size: int, similarity: float, recall: float) -> tuple[int, int, int]:
    """Bits of the prefix, number of tries and Hamming budget for ``n`` fingerprints of ``size`` bits.

    Sets of Jaccard similarity s have a cosine of 2s / (1 + s), and a bit differs with the angle's share of a half turn.  Prefixes
    leave about four fingerprints in a group; tries are as many as it takes for a pair to share a prefix with chance
    ``recall``; the budget lies 2.5 deviations above the mean, as whole sets are compared afterwards.
    """
    differ = math.acos(2 * similarity / (1 + similarity)) / math.pi
    bits = min(56, max(8, math.ceil(math.log2(max(2, n))) - 2))
    tries = math.ceil(math.log(1 - recall) / math.log1p(-((1 - differ) ** bits)))
    return bits, tries, int(size * differ + 2.5 * math.sqrt(size * differ * (1 - differ)))


def leaf_pairs(alo: np.ndarray, ahi: np.ndarray, blo: np.ndarray, bhi: np.ndarray) -> tuple[np.ndarray, np.ndarray]:
    """All pairs of a leaf below the first and one below the second node, once each where the nodes are one."""
    across = bhi - blo
    size = (ahi - alo) * across
    of = np.repeat(np.arange(len(size)), size)
    at = np.arange(len(of)) - np.repeat(np.cumsum(size) - size, size)
    a, b = alo[of] + at // across[of], blo[of] + at % across[of]
    once = (a < b) | (alo[of] != blo[of])
    return a[once], b[once]


def links_in_groups(group: np.ndarray, raw: np.ndarray, budget: int) -> list[tuple[int, int]]:
    """Spanning links between rows of one group at most ``budget`` bits apart: positions in the input.

    Rows are sorted, so a node of a group's trie is a range, and the bit of a depth, summed along the rows, tells where
    the node splits.  Pairs of nodes are walked together; unlike branches cost an error, and a pair is dropped once it
    has spent more than the budget or all its leaves are in one class.
    """
    words = np.ascontiguousarray(raw).view(">u8").astype(np.uint64)
    order = np.lexsort((*words.T[::-1], group))
    words, group = words[order], group[order]
    n = len(words)
    cut = np.flatnonzero(np.concatenate(([True], group[1:] != group[:-1], [True])))
    lo, hi = cut[:-1], cut[1:]
    lo, hi = lo[hi - lo > 1], hi[hi - lo > 1]
    classes, links, held = Classes(n), [], {}

    def ones_before(d: int) -> np.ndarray:
        found = held.get(d)
        if found is None:
            if len(held) >= HELD_DEPTHS:
                held.pop(next(iter(held)))
            bit = (words[:, d >> 6] >> np.uint64(63 - (d & 63))) & np.uint64(1)
            found = held[d] = np.concatenate(([0], np.cumsum(bit, dtype=np.int64)))
        return found

    stack = [(lo[i : i + FRONTIER], hi[i : i + FRONTIER], lo[i : i + FRONTIER], hi[i : i + FRONTIER], 0, np.zeros(len(lo[i : i + FRONTIER]), np.int16)) for i in range(0, len(lo), FRONTIER)]
    while stack:
        alo, ahi, blo, bhi, d, err = stack.pop()
        open_ = ~classes.one_class(alo, ahi, blo, bhi)
        alo, ahi, blo, bhi, err = alo[open_], ahi[open_], blo[open_], bhi[open_], err[open_]
        few = (ahi - alo) * (bhi - blo) <= FEW
        if few.any():
            a, b = leaf_pairs(alo[few], ahi[few], blo[few], bhi[few])
            near = np.bitwise_count(words[a] ^ words[b]).sum(axis=1, dtype=np.int64) <= budget
            near &= classes.root[a] != classes.root[b]
            links += classes.link(a[near], b[near])
            alo, ahi, blo, bhi, err = alo[~few], ahi[~few], blo[~few], bhi[~few], err[~few]
        if not len(alo):
            continue
        if d == words.shape[1] * 64:  # equal fingerprints
            own = np.concatenate([np.arange(x, y) for x, y in zip(alo, ahi)])
            links += classes.link(np.concatenate((alo, np.repeat(alo, ahi - alo))), np.concatenate((blo, own)))
            continue
        ones = ones_before(d)
        amid, bmid = ahi - (ones[ahi] - ones[alo]), bhi - (ones[bhi] - ones[blo])
        own = (alo == blo) & (ahi == bhi)
        cross = err < budget
        sides = [
            (alo[cross], amid[cross], bmid[cross], bhi[cross], err[cross] + 1),
            (amid[cross & ~own], ahi[cross & ~own], blo[cross & ~own], bmid[cross & ~own], err[cross & ~own] + 1),
            (amid, ahi, bmid, bhi, err),
            (alo, amid, blo, bmid, err),
        ]
        # One block for all four, so that blocks stay long; like branches stand last and are walked first.
        al, ah, bl, bh, e = (np.concatenate(c) for c in zip(*sides))
        k = np.flatnonzero((al < ah) & (bl < bh) & ~((al == bl) & (ah == bh) & (ah - al == 1)))
        for i in range(0, len(k), FRONTIER):
            j = k[i : i + FRONTIER]
            stack.append((al[j], ah[j], bl[j], bh[j], d + 1, e[j].astype(np.int16)))
    return [(int(order[a]), int(order[b])) for a, b in links]
