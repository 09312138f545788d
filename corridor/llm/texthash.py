"""Words and word n-grams of Arrow text columns as 64-bit hashes, computed on whole buffers.

A word is a run of bytes outside space and the controls 9 to 13.  Its hash is a polynomial in an odd
base modulo 2**64, read off one running sum per piece of text, then mixed; equal words have equal
hashes, and different words share one with a chance of about 2**-64.
"""

from __future__ import annotations

from dataclasses import dataclass

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame

PIECE = 1 << 18
BASE = np.uint64(0x9E3779B97F4A7C15)
BASE_INVERSE = np.uint64(pow(0x9E3779B97F4A7C15, -1, 1 << 64))
_SPACE = np.zeros(256, bool)
_SPACE[[9, 10, 11, 12, 13, 32]] = True
_LOWER = np.arange(256, dtype=np.uint8)
_LOWER[65:91] += 32
_powers: dict[str, np.ndarray] = {}


def mix(x: np.ndarray) -> np.ndarray:
    """A bijection of 64-bit integers that spreads every input bit."""
    x = x.astype(np.uint64, copy=True)
    x ^= x >> np.uint64(30)
    x *= np.uint64(0xBF58476D1CE4E5B9)
    x ^= x >> np.uint64(27)
    x *= np.uint64(0x94D049BB133111EB)
    x ^= x >> np.uint64(31)
    return x


def _power_tables(n: int) -> tuple[np.ndarray, np.ndarray]:
    if _powers.get("up") is None or len(_powers["up"]) < n:
        size = max(n, PIECE + 1)
        up, down = np.full(size, BASE, np.uint64), np.full(size, BASE_INVERSE, np.uint64)
        up[0] = down[0] = 1
        _powers["up"], _powers["down"] = np.cumprod(up, dtype=np.uint64), np.cumprod(down, dtype=np.uint64)
    return _powers["up"], _powers["down"]


@dataclass
class Words:
    """Words of a batch of texts: hash, byte span in ``data``, and first word of each text."""

    data: np.ndarray
    hashes: np.ndarray
    starts: np.ndarray
    ends: np.ndarray
    first: np.ndarray  # len(texts) + 1

    def counts(self) -> np.ndarray:
        return np.diff(self.first)


def text_buffers(texts: pa.Array) -> tuple[np.ndarray, np.ndarray]:
    """UTF-8 bytes and len + 1 offsets of a string array; null is empty."""
    if texts.type != pa.large_string():
        texts = texts.cast(pa.large_string())
    if isinstance(texts, pa.ChunkedArray):
        texts = texts.combine_chunks()
    if texts.null_count:
        texts = texts.fill_null("")
    _, offsets, data = texts.buffers()
    off = np.frombuffer(offsets, np.int64)[texts.offset : texts.offset + len(texts) + 1] if len(texts) else np.zeros(1, np.int64)
    raw = np.frombuffer(data, np.uint8) if data is not None else np.zeros(0, np.uint8)
    return raw[off[0] : off[-1]], off - off[0]


def words(texts: pa.Array, lower: bool = False) -> Words:
    """Words of every text of the batch; ``lower`` folds A-Z first."""
    data, off = text_buffers(texts)
    hashes, starts, ends = [], [], []
    at, n = 0, len(data)
    while at < n:
        stop = min(n, at + PIECE)
        while stop < n and not _SPACE[data[stop]]:  # a piece ends before white space or a text
            nxt = off[np.searchsorted(off, stop)]
            gap = np.flatnonzero(_SPACE[data[stop : min(n, stop + PIECE)]])
            stop = int(min(nxt, stop + (gap[0] if len(gap) else PIECE), n))
            if stop == nxt:
                break
        part = data[at:stop]
        lo, hi = np.searchsorted(off, (at, stop))
        cuts = np.unique(off[lo : hi + 1])
        cuts = cuts[(cuts > at) & (cuts < stop)] - at
        solid = ~_SPACE[part]
        begin = solid.copy()
        begin[1:] &= ~solid[:-1]
        begin[cuts] = solid[cuts]
        finish = solid.copy()
        finish[:-1] &= ~solid[1:]
        finish[cuts - 1] = solid[cuts - 1]
        s, e = np.flatnonzero(begin), np.flatnonzero(finish) + 1
        up, down = _power_tables(len(part) + 1)
        value = (_LOWER[part] if lower else part).astype(np.uint64)
        value += np.uint64(1)
        value *= up[: len(part)]
        total = np.zeros(len(part) + 1, np.uint64)
        np.cumsum(value, out=total[1:])
        h = (total[e] - total[s]) * down[s]
        hashes.append(mix(h ^ ((e - s).astype(np.uint64) << np.uint64(56))))
        starts.append(s + at)
        ends.append(e + at)
        at = stop
    cat = lambda parts, kind: np.concatenate(parts) if parts else np.zeros(0, kind)
    s = cat(starts, np.int64)
    return Words(data, cat(hashes, np.uint64), s, cat(ends, np.int64), np.searchsorted(s, off))


def windows(w: Words, k: int) -> tuple[np.ndarray, np.ndarray]:
    """Hash of every run of ``k`` words inside one text, and the index of the run's first word."""
    n = len(w.hashes)
    if n < k:
        return np.zeros(0, np.uint64), np.zeros(0, np.int64)
    left = np.repeat(w.first[1:], w.counts()) - np.arange(n)  # words from here to the end of the text
    at = np.flatnonzero(left >= k)
    h = np.zeros(n - k + 1, np.uint64)
    for j in range(k):
        h *= BASE
        h += w.hashes[j : n - k + 1 + j]
    return mix(h[at]), at


def gram_sets(w: Words, k: int) -> tuple[np.ndarray, np.ndarray]:
    """Distinct k-word shingles of each text, ordered by text and hash: (hash, index of the text).

    A text with fewer than k words has its whole sequence as its one shingle; a text without words has none.
    """
    h, at = windows(w, k)
    doc = np.searchsorted(w.first, at, side="right") - 1
    c = w.counts()
    short = np.flatnonzero((c > 0) & (c < k))
    if len(short):
        extra = np.zeros(len(short), np.uint64)
        for j in range(k - 1):
            has = c[short] > j
            extra[has] = extra[has] * BASE + w.hashes[w.first[short[has]] + j]
        extra = mix(extra ^ (c[short].astype(np.uint64) << np.uint64(48)) ^ np.uint64(0x5851F42D4C957F2D))
        h, doc = np.concatenate([h, extra]), np.concatenate([doc, short])
    order = np.lexsort((h, doc))
    h, doc = h[order], doc[order]
    if len(h):
        new = np.ones(len(h), bool)
        new[1:] = (h[1:] != h[:-1]) | (doc[1:] != doc[:-1])
        h, doc = h[new], doc[new]
    return h, doc


def slices(texts: pa.Array, limit: int = 1 << 20):
    """Split a text column into slices of about ``limit`` bytes: (first row, end row)."""
    _, off = text_buffers(texts)
    at = 0
    while at < len(texts):
        end = int(np.searchsorted(off, off[at] + limit, side="right")) - 1
        end = max(at + 1, min(end, len(texts)))
        yield at, end
        at = end


BATCH_ROWS = 1000


def bounded(df: DataFrame) -> DataFrame:
    """``df``, with Arrow batches of its session bounded to BATCH_ROWS rows: documents are long, and a default batch of them isn't small."""
    name = "spark.sql.execution.arrow.maxRecordsPerBatch"
    conf = df.sparkSession.conf
    if not 0 < int(conf.get(name)) <= BATCH_ROWS:
        conf.set(name, str(BATCH_ROWS))
    return df


def unused(name: str, df: DataFrame) -> str:
    """``name``, with underscores before it while the frame has a column of that name."""
    taken = {c.lower() for c in df.columns}
    while name.lower() in taken:
        name = f"_{name}"
    return name


def small(batches, rows: int = 1024):
    """The same rows in batches of at most ``rows``, so that what is made of one stays small."""
    for batch in batches:
        for a in range(0, batch.num_rows, rows):
            yield batch.slice(a, rows)


def even_keys(n: int) -> np.ndarray:
    """For each of n hash partitions, an integer that Spark's hash of an int column (Murmur3, seed 42) puts there."""
    out, low = np.full(n, -1, np.int64), 0
    while (out < 0).any():
        x = np.arange(low, low + 8 * n + 64, dtype=np.uint32)
        k = x * np.uint32(0xCC9E2D51)
        k = (k << np.uint32(15) | k >> np.uint32(17)) * np.uint32(0x1B873593)
        h = np.uint32(42) ^ k
        h = (h << np.uint32(13) | h >> np.uint32(19)) * np.uint32(5) + np.uint32(0xE6546B64)
        h ^= np.uint32(4)
        h ^= h >> np.uint32(16)
        h *= np.uint32(0x85EBCA6B)
        h ^= h >> np.uint32(13)
        h *= np.uint32(0xC2B2AE35)
        h ^= h >> np.uint32(16)
        at = h.view(np.int32).astype(np.int64) % n
        first, where = np.unique(at, return_index=True)
        gone = out[first] < 0
        out[first[gone]] = x[where[gone]]
        low += len(x)
    return out


def tidy(f):
    """A batch function that gives freed memory back to the system when it ends: idle workers of one stage stay beside the next one's."""

    def run(data):
        out = f(data)
        if isinstance(out, pa.Table):
            release()
            return out
        return _each(out)

    def _each(batches):
        try:
            yield from batches
        finally:
            release()

    return run


def release() -> None:
    import ctypes
    import gc

    gc.collect()
    pa.default_memory_pool().release_unused()
    try:
        ctypes.CDLL("libc.so.6").malloc_trim(0)
    except (OSError, AttributeError):  # another C library
        pass
