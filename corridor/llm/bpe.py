"""Byte-level BPE with a hierarchical-bitmap rank queue.

A pre-token is a linked list of parts, at first its bytes.  Every adjacent pair that is a vocabulary entry waits in the bucket of
its rank.  Which buckets are in use is a bitmap of 64-bit words with a summary bitmap above it, so that two find-first-set
steps give the lowest rank.  The leftmost position of that bucket merges; its neighbours' new pairs queue up, and what
was queued for pairs that are gone is recognised by the position's present rank and skipped.  Each position
enters a bucket a constant number of times per merge, so a pre-token of n bytes takes O(n log n) however long it is.

Most pre-tokens of a corpus repeat, so a task keeps the ids of those it has met lately, up to a fixed number.
"""

from __future__ import annotations

import base64
import hashlib
import re
import struct
from heapq import heappop, heappush

import numpy as np
import pyarrow as pa
import regex
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from corridor.llm.texthash import bounded, small, tidy

REMEMBERED, LONGEST = 1 << 18, 64
_BITS = [1 << i for i in range(1 << 12)]  # ranks below 2**18


class Starts:
    """Ranks of single bytes, and of pairs of bytes by their 16 bits, none as -1."""

    def __init__(self, ranks: dict[bytes, int]) -> None:
        self.one = [ranks[bytes([b])] for b in range(256)]
        self.two = [ranks.get(bytes([a, b]), -1) for a in range(256) for b in range(256)]


def merge(raw: bytes, ranks: dict[bytes, int], starts: Starts) -> list[int]:
    """Ids of one pre-token.

    ``buckets`` has the waiting positions of each rank as a heap, so that the leftmost comes first; ``words`` has the used ranks as 64-bit
    words, ``summary`` the used words.  Queue steps are written out in place: this is the innermost loop of encoding.
    """
    whole = ranks.get(raw)
    if whole is not None:
        return [whole]
    n, get, one, two = len(raw), ranks.get, starts.one, starts.two
    ids = [one[b] for b in raw]
    after, before = list(range(1, n + 1)), list(range(-1, n - 1))
    waits = [two[a << 8 | b] for a, b in zip(raw, raw[1:], strict=False)]  # rank of the pair that starts here now
    waits.append(-1)
    buckets: dict[int, list[int]] = {}
    words: dict[int, int] = {}
    summary = 0
    for i, r in enumerate(waits):
        if r >= 0:
            if r in buckets:
                buckets[r].append(i)  # ascending, so a heap
            else:
                buckets[r] = [i]
                w = r >> 6
                words[w] = words.get(w, 0) | _BITS[r & 63]
                summary |= _BITS[w]
    while summary:
        top = summary & -summary
        w = top.bit_length() - 1
        bits = words[w]
        low = bits & -bits
        rank = (w << 6) + low.bit_length() - 1
        bucket = buckets[rank]
        if len(bucket) > 1:
            i = heappop(bucket)
        else:
            i = bucket[0]
            del buckets[rank]
            bits ^= low
            words[w] = bits
            if not bits:
                summary ^= top
        if waits[i] != rank:  # stale
            continue
        j = after[i]
        k = after[j]
        ids[i], after[i], waits[j], waits[i] = rank, k, -1, -1
        h = before[i]
        if k < n:
            before[k] = i
            r = get(raw[i : after[k]])
            if r is not None:
                waits[i] = r
                if r in buckets:
                    heappush(buckets[r], i)
                else:
                    buckets[r] = [i]
                    w = r >> 6
                    words[w] = words.get(w, 0) | _BITS[r & 63]
                    summary |= _BITS[w]
        elif h < 0:  # one part is left
            break
        if h >= 0:
            r = get(raw[h:k])
            if r is None:
                waits[h] = -1
            elif waits[h] != r:
                waits[h] = r
                if r in buckets:
                    heappush(buckets[r], h)
                else:
                    buckets[r] = [h]
                    w = r >> 6
                    words[w] = words.get(w, 0) | _BITS[r & 63]
                    summary |= _BITS[w]
    out, i = [], 0
    while i < n:
        out.append(ids[i])
        i = after[i]
    return out


class _Memory(dict):
    """Pre-token to ids as little-endian bytes.  When full, this becomes the elder generation, from which what is still in use comes back."""

    def __init__(self, ranks: dict[bytes, int], starts: Starts | None = None) -> None:
        self.ranks, self.starts, self.elder = ranks, starts or Starts(ranks), {}

    def __missing__(self, token: str) -> bytes:
        ids = self.elder.get(token)
        if ids is None:
            ids = pack(merge(token.encode(), self.ranks, self.starts))
            if len(token) > LONGEST:
                return ids
        if len(self) >= REMEMBERED:
            self.elder = dict(self)
            self.clear()
        self[token] = ids
        return ids


def pack(ids: list[int]) -> bytes:
    return struct.pack(f"<{len(ids)}I", *ids)


def splitter(pattern: str):
    """findall of a pattern.

    Texts of Latin-1 characters, most of them, go to the standard library's quicker engine, with the classes that the pattern names
    spelled out as they are in that range; others, and patterns with other escapes, to the full one.
    """
    full = regex.compile(pattern).findall
    classes = {name: "".join(re.escape(c) for c in map(chr, range(256)) if regex.fullmatch(name, c)) for name in (r"\p{L}", r"\p{N}", r"\s")}
    plain = pattern.replace(r"\S", f"[^{classes[chr(92) + 's']}]")
    for name, members in classes.items():
        plain = re.sub(r"(\[\^?(?:[^\]\\]|\\.(?:\{\w\})?)*\])|" + re.escape(name), lambda m, name=name, members=members: m[1].replace(name, members) if m[1] else f"[{members}]", plain)
    if re.search(r"\\[a-zA-Z]", re.sub(r"\\[\t-\r\x1c-\x1f\x85\xa0 ]", "", plain)):
        return full
    latin = re.compile(plain).findall

    def split(text: str) -> list[str]:
        try:
            text.encode("latin-1")
        except UnicodeEncodeError:
            return full(text)
        return latin(text)

    return split


class Codec:
    """Encoder and decoder for one vocabulary of ranks and one pattern."""

    def __init__(self, path: str, pattern: str) -> None:
        with open(path, "rb") as f:  # part of the software, as installed on every machine
            self.ranks = {base64.b64decode(a): int(b) for a, b in map(bytes.split, f)}
        self.parts = [b""] * (max(self.ranks.values()) + 1)
        for raw, i in self.ranks.items():
            self.parts[i] = raw
        self.split = splitter(pattern)
        self.starts = Starts(self.ranks)
        self.memory = _Memory(self.ranks, self.starts)

    def encode(self, text: str) -> bytes:
        """Ids as little-endian unsigned 32-bit integers."""
        return b"".join(map(self.memory.__getitem__, self.split(text)))

    def decode(self, ids: bytes) -> bytes:
        return b"".join(map(self.parts.__getitem__, np.frombuffer(ids, "<u4").tolist()))


_codecs: dict[tuple[str, str], Codec] = {}


def codec(path: str | None = None, pattern: str | None = None) -> Codec:
    """The codec of a vocabulary file; one is kept in each process."""
    import public_tokenizers

    key = (path or public_tokenizers.path("byte_bpe_50k.tiktoken"), pattern or public_tokenizers.PATTERN)
    if key not in _codecs:
        _codecs[key] = Codec(*key)
    return _codecs[key]


def encode_documents(docs: DataFrame, path: str | None = None, pattern: str | None = None, with_ids: bool = True) -> DataFrame:
    """doc_id, n_tokens, ids_sha256, decoded_sha256 and, if wanted, ids of every row of ``docs(doc_id, text)``.

    Each match of the pattern is encoded by itself, without special tokens; the ids are decoded again for the second digest.
    A null or empty text has no ids.  Rows may repeat; a null doc_id stays null.
    """

    def run(batches):
        c = codec(path, pattern)
        c.memory = _Memory(c.ranks, c.starts)  # a task's own; it goes with the task
        for batch in small(batches):
            n, digest, back, ids = [], [], [], []
            for text in batch.column(1):
                raw = c.encode(text.as_py() or "")
                n.append(len(raw) // 4)
                digest.append(hashlib.sha256(raw).hexdigest())
                back.append(hashlib.sha256(c.decode(raw)).hexdigest())
                if with_ids:
                    ids.append(raw)
            columns = [batch.column(0), pa.array(n, pa.int64()), pa.array(digest, pa.string()), pa.array(back, pa.string())]
            names = ["doc_id", "n_tokens", "ids_sha256", "decoded_sha256"]
            if with_ids:
                offsets = np.concatenate([[0], np.cumsum(n)]).astype(np.int32)
                columns.append(pa.ListArray.from_arrays(pa.array(offsets), pa.array(np.frombuffer(b"".join(ids), "<i4"))))
                names.append("ids")
            yield pa.RecordBatch.from_arrays(columns, names)
        c.memory = _Memory(c.ranks, c.starts)

    schema = "doc_id long, n_tokens long, ids_sha256 string, decoded_sha256 string" + ", ids array<int>" * with_ids
    return bounded(docs).select(F.col("doc_id").cast("long").alias("doc_id"), F.col("text").cast("string").alias("text")).mapInArrow(tidy(run), schema)
