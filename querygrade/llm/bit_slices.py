"""Bit-sliced Hamming comparison of 64-bit fingerprints.

A block of fingerprints is stored as 64 vertical bit planes: word ``w`` of plane ``k`` holds bit ``k``
of fingerprints ``64*w .. 64*w+63``.  A query differs from 64 of them at once where
``plane ^ query_bit`` is set; these differences are added into carry-save counters that are planes
themselves (ones, twos, fours ...).  A counter that passes the radius sets a sticky plane, and a block
is abandoned as soon as every lane of it is past the radius.
"""

from __future__ import annotations

import numpy as np

FULL = np.uint64(0xFFFFFFFFFFFFFFFF)


def bit_planes(prints: np.ndarray) -> np.ndarray:
    """(64, ceil(n/64)) planes of n fingerprints; lane j of word w is bit j, least bit first."""
    n = len(prints)
    bits = np.unpackbits(np.ascontiguousarray(prints.astype("<u8")).view(np.uint8).reshape(n, 8), axis=1, bitorder="little").T
    pad = -n % 64
    if pad:
        bits = np.concatenate([bits, np.zeros((64, pad), np.uint8)], axis=1)
    return np.packbits(np.ascontiguousarray(bits), axis=1, bitorder="little").view("<u8").astype(np.uint64)


def near_lanes(planes: np.ndarray, queries: np.ndarray, radius: int, check_every: int = 8) -> np.ndarray:
    """(m, words) lanes within ``radius`` of each query; planes may be (64, words) or (64, m, words)."""
    shared = planes.ndim == 2
    shape = (len(queries), planes.shape[-1])
    counters = [np.zeros(shape, np.uint64) for _ in range(max(1, int(radius).bit_length()))]
    past = np.zeros(shape, np.uint64)
    for k in range(64):
        mask = np.where((queries >> np.uint64(k)) & np.uint64(1), FULL, np.uint64(0))[:, None]
        carry = (planes[k][None, :] if shared else planes[k]) ^ mask
        for plane in counters:
            up = plane & carry
            plane ^= carry
            carry = up
        past |= carry
        if k % check_every == check_every - 1:
            over = past | _above(counters, radius)
            if (over == FULL).all():
                return np.zeros(shape, np.uint64)
    return ~(past | _above(counters, radius))


def _above(counters: list[np.ndarray], radius: int) -> np.ndarray:
    """Lanes whose counter is greater than the radius, compared from the high bit down."""
    above, equal = np.zeros_like(counters[0]), np.full_like(counters[0], FULL)
    for k in reversed(range(len(counters))):
        if radius >> k & 1:
            equal &= counters[k]
        else:
            above |= equal & counters[k]
            equal &= ~counters[k]
    return above


def lanes_to_bool(lanes: np.ndarray, n: int) -> np.ndarray:
    flat = np.ascontiguousarray(lanes.astype("<u8")).view(np.uint8).reshape(lanes.shape[0], -1)
    return np.unpackbits(flat, axis=1, bitorder="little")[:, :n].astype(bool)


def forest(prints: np.ndarray, radius: int, step: int = 64) -> tuple[np.ndarray, np.ndarray]:
    """(child, parent) positions: a spanning forest of the graph of fingerprints within ``radius``.

    Breadth first; each position is a query once, against the lanes that no tree holds yet.
    """
    n = len(prints)
    parent = np.full(n, -1)
    free = np.ones(n, bool)
    rest = np.arange(n)
    planes = bit_planes(prints)
    for seed in range(n):
        if not free[seed]:
            continue
        free[seed] = False
        front = [seed]
        while front and free.any():
            if free.sum() * 2 < len(rest):
                rest = np.flatnonzero(free)
                planes = bit_planes(prints[rest])
            now, front = np.array(front[:step]), front[step:]
            hit = lanes_to_bool(near_lanes(planes, prints[now], radius), len(rest)) & free[rest][None, :]
            got = np.flatnonzero(hit.any(axis=0))
            parent[rest[got]] = now[hit[:, got].argmax(axis=0)]
            free[rest[got]] = False
            front += rest[got].tolist()
    child = np.flatnonzero(parent >= 0)
    return child, parent[child]


def small_groups_links(prints: np.ndarray, starts: np.ndarray, sizes: np.ndarray, radius: int) -> tuple[np.ndarray, np.ndarray]:
    """All pairs of positions within ``radius`` inside many groups of at most 64, one word for each group."""
    groups, widest = len(starts), int(sizes.max())
    lanes = np.zeros((groups, 64), np.uint64)
    inside = np.arange(64)[None, :] < sizes[:, None]
    at = starts[:, None] + np.arange(64)[None, :]
    lanes[inside] = prints[at[inside]]
    planes = bit_planes(lanes.reshape(-1))[:, :, None]
    valid = np.where(sizes == 64, FULL, (np.uint64(1) << (sizes % 64).astype(np.uint64)) - np.uint64(1))
    left, right = [], []
    for j in range(widest - 1):
        live = np.flatnonzero(sizes > j + 1)
        hit = near_lanes(planes[:, live], lanes[live, j], radius)
        later = hit[:, 0] & valid[live] & ~((np.uint64(2) << np.uint64(j)) - np.uint64(1))
        some = np.flatnonzero(later)
        if not len(some):
            continue
        row, lane = np.nonzero(lanes_to_bool(later[some][:, None], 64))
        left.append(starts[live[some[row]]] + j)
        right.append(starts[live[some[row]]] + lane)
    return (np.concatenate(left), np.concatenate(right)) if left else (np.zeros(0, int), np.zeros(0, int))
