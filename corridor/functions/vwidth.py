"""Shared-width code: groups of whole numbers, each group with the bits of its largest member.

A group has a header (width and length class) and its members at that width.  The cuts between groups are the cheapest over all
ways to cut, by dynamic programming over the end of the last group.
"""

from __future__ import annotations

import numpy as np

LENGTHS = (1, 2, 3, 4, 5, 6, 7, 8, 10, 12, 16, 20, 24, 32, 48, 64)
WIDTH_BITS, CLASS_BITS = 6, 4
HEADER = WIDTH_BITS + CLASS_BITS


def bit_lengths(u: np.ndarray) -> np.ndarray:
    """Bits of each unsigned number, none for zero; exact up to 2**63."""
    u = u.astype(np.uint64)
    out = np.zeros(u.shape, np.int64)
    for s in (32, 16, 8, 4, 2, 1):
        big = u >= np.uint64(1 << s)
        out[big] += s
        u = np.where(big, u >> np.uint64(s), u)
    return out + (u > 0)


def _window_max(b: np.ndarray) -> np.ndarray:
    """For each class the largest width among the ``length`` numbers that end at each place; too short ones get -1."""
    out = np.full((len(LENGTHS), len(b)), -1, np.int64)
    for c, length in enumerate(LENGTHS):
        if length <= len(b):
            out[c, length - 1 :] = np.lib.stride_tricks.sliding_window_view(b, length).max(axis=1)
    return out


def cuts(u: np.ndarray) -> tuple[list[int], int]:
    """(length classes of the cheapest cut, its bits)."""
    n = len(u)
    if not n:
        return [], 0
    widths = _window_max(bit_lengths(u))
    cost = HEADER + widths * np.array(LENGTHS)[:, None]
    cost[widths < 0] = 1 << 50
    rows = cost.T.tolist()
    best, pick = [0] * (n + 1), [0] * (n + 1)
    for i, row in enumerate(rows, 1):
        low, at = 1 << 60, 0
        for c, length in enumerate(LENGTHS):
            if length > i:
                break
            v = best[i - length] + row[c]
            if v < low:
                low, at = v, c
        best[i], pick[i] = low, at
    out, i = [], n
    while i:
        out.append(pick[i])
        i -= LENGTHS[pick[i]]
    return out[::-1], best[n]


def cuts_many(b: np.ndarray) -> np.ndarray:
    """For lists of n numbers, as rows of their bit lengths, the class of the cheapest cut's last group at each place; all rows go step by step."""
    m, n = b.shape
    b = np.ascontiguousarray(b.T, np.int32)
    low = 1 << 28
    cost = np.full((n, len(LENGTHS), m), low, np.int32)  # the class is in the low bits: of equal costs the first class wins
    widest = {1: b}
    for c, length in enumerate(LENGTHS):
        if length > n:
            break
        if c:
            a = LENGTHS[c - 1]
            w, rest = widest[a], length - a  # a window is two shorter ones, one after the other
            widest[length] = np.maximum(w[rest:], widest[rest][: len(w) - rest])
        cost[length - 1 :, c] = HEADER + widest[length] * length << 4 | c
    best = np.zeros((n + 1 + LENGTHS[-1], m), np.int32)  # of the first numbers, after places that no group reaches
    before = LENGTHS[-1] + 1 - np.array(LENGTHS)
    pick = np.empty((n, m), np.uint8)
    for i in range(n):
        v = (best[before + i] + cost[i]).min(axis=0)
        pick[i] = v & 15
        best[LENGTHS[-1] + i + 1] = v & ~15
    return pick.T


def size(u: np.ndarray) -> int:
    """Bits of the cheapest code."""
    return cuts(np.asarray(u))[1]


def encode(u: np.ndarray) -> bytes:
    """The code of a list of unsigned numbers; its length isn't stored."""
    u = np.asarray(u, np.uint64)
    classes, _ = cuts(u)
    return _coded(u, bit_lengths(u), classes)


def encode_many(rows: list[np.ndarray], at_once: int = 128) -> list[bytes]:
    """The codes of many lists; those of one length are cut together."""
    out: list = [b""] * len(rows)
    by_length: dict[int, list[int]] = {}
    for i, u in enumerate(rows):
        by_length.setdefault(len(u), []).append(i)
    for n, which in by_length.items():
        for a in range(0, len(which) if n else 0, at_once):
            part = which[a : a + at_once]
            u = np.stack([np.asarray(rows[i], np.uint64) for i in part])
            b = bit_lengths(u)
            for i, v, w, pick in zip(part, u, b, cuts_many(b), strict=True):
                pick, classes, at = pick.tolist(), [], n
                while at:
                    classes.append(pick[at - 1])
                    at -= LENGTHS[classes[-1]]
                out[i] = _coded(v, w, classes[::-1])
    return out


def _coded(u: np.ndarray, sizes: np.ndarray, classes: list[int]) -> bytes:
    if not classes:
        return b""
    lengths = np.array(LENGTHS)[classes]
    starts = np.concatenate([[0], np.cumsum(lengths)[:-1]])
    widths = np.maximum.reduceat(sizes, starts)
    # items in order: a header before each group's members
    n = len(u) + len(classes)
    at = starts + np.arange(len(classes))
    value, width = np.zeros(n, np.uint64), np.zeros(n, np.int64)
    member = np.ones(n, bool)
    member[at] = False
    value[at], width[at] = (widths | np.array(classes) << WIDTH_BITS).astype(np.uint64), HEADER
    value[member], width[member] = u, np.repeat(widths, lengths)
    item = np.repeat(np.arange(n), width)
    bit = np.arange(len(item)) - np.repeat(np.cumsum(width) - width, width)
    return np.packbits(((value[item] >> bit.astype(np.uint64)) & np.uint64(1)).astype(np.uint8), bitorder="little").tobytes()


def decode(raw: bytes, n: int) -> np.ndarray:
    """The n numbers of a code."""
    bits = np.unpackbits(np.frombuffer(raw, np.uint8), bitorder="little")
    out, at, i = np.zeros(n, np.uint64), 0, 0
    powers = np.uint64(1) << np.arange(64, dtype=np.uint64)
    while i < n:
        width = int(bits[at : at + WIDTH_BITS] @ powers[:WIDTH_BITS])
        length = LENGTHS[int(bits[at + WIDTH_BITS : at + HEADER] @ powers[:CLASS_BITS])]
        at += HEADER
        out[i : i + length] = bits[at : at + width * length].reshape(length, width).astype(np.uint64) @ powers[:width] if width else 0
        at += width * length
        i += length
    return out


def pack_fixed(u: np.ndarray, width: int) -> bytes:
    """Numbers at one width."""
    if not width:
        return b""
    bits = (np.asarray(u, np.uint64)[:, None] >> np.arange(width, dtype=np.uint64)) & np.uint64(1)
    return np.packbits(bits.astype(np.uint8).ravel(), bitorder="little").tobytes()


def unpack_fixed(raw: bytes, n: int, width: int) -> np.ndarray:
    if not width:
        return np.zeros(n, np.uint64)
    bits = np.unpackbits(np.frombuffer(raw, np.uint8), bitorder="little")[: n * width].reshape(n, width)
    return bits.astype(np.uint64) @ (np.uint64(1) << np.arange(width, dtype=np.uint64))


def zigzag(i: np.ndarray, kind: str = "dense") -> np.ndarray:
    i = np.asarray(i, np.int64)
    return np.where(i >= 0, 2 * i, -2 * i + (1 if kind == "sparse" else -1)).astype(np.uint64)


def unzigzag(u: np.ndarray, kind: str = "dense") -> np.ndarray:
    u = np.asarray(u).astype(np.int64)
    return np.where(u % 2 == 0, u // 2, -((u + (1 if kind == "dense" else -1)) // 2))
