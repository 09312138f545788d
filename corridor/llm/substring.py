"""Removal of word sequences that also occur in an earlier document, by prefix-partitioned suffix trees.

Symbols are words, suffixes start at words, and only nodes at least a window deep matter.  Documents are dealt once, by a hash
of their text, to parts of bounded bytes; every step reads that one exchange.

1. Prefix counts.  Suffixes are counted by a cell of their first ``PREFIX`` words, over all documents, in a table of fixed
   size.  Cells are dealt to groups until a group's budget is full; a cell above the budget is extended, that is, its
   suffixes are told apart by all words of the window (the longer prefix) and go to several groups.
2. Lone suffixes go.  A part sends a short print of each of its windows once, as gaps of sorted numbers, and is told by a bit for each
   which of them another part has too.  The others can't lie under a node of two leaves, and aren't sent on.  Prints that meet by
   chance only let a suffix through.
3. Subtrees.  The suffixes left go to the group of their prefix as the words themselves, down to the window's depth, coded by a
   dictionary that comes along.  A group sorts its suffixes by words, takes the longest common prefix of each with the one
   before, and so has the subtree: suffixes between which it never falls below the window are the leaves of one deep
   internal node.  Of each node it finds the smallest document and tells the others.  A part sends a path once, for the smallest
   document it has; its other documents with that path have a smaller one beside them.
4. Cutting.  Told windows meet their part again, which finds those with a smaller document beside them itself; the words they
   cover go.  Nodes of adjoining suffixes make one maximal repeat.
"""

from __future__ import annotations

import hashlib
from collections.abc import Callable
from dataclasses import dataclass

import numpy as np
import pyarrow as pa
import pyarrow.compute as pc
import zstandard
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from corridor.llm import texthash as T
from corridor.runtime import cut

PREFIX, CELLS = 3, 1 << 14
GROUP_WINDOWS = 1 << 21
PART_BYTES, LEAST_PARTS = 6 << 20, 48
BROADCAST_ROWS = 1 << 20
PRINT_BITS, PRINT_GROUP = 24, 1 << 18  # of a print, and prints that share a space of that size, about
MOST_TASKS = 1 << 13  # of step 2


def _runs(keys: np.ndarray) -> np.ndarray:
    """Marks the first item of each run of a sorted array."""
    new = np.ones(len(keys), bool)
    new[1:] = keys[1:] != keys[:-1]
    return new


def _spans(keys: np.ndarray) -> tuple[np.ndarray, list[tuple[int, int]]]:
    """The values of a sorted array, and where each begins and ends."""
    full, at = np.unique(keys, return_index=True)
    bounds = [*at.tolist(), len(keys)]
    return full, list(zip(bounds, bounds[1:]))


def prefix_counts(docs: DataFrame, window: int) -> tuple[np.ndarray, int]:
    """Number of windows in each cell, and bytes of text, over all documents."""

    def count(batches):
        total, size = np.zeros(CELLS + 1, np.int64), 0
        for batch in batches:
            for a, b in T.slices(batch.column(0)):
                w = T.words(batch.column(0)[a:b])
                _, at = T.windows(w, window)
                total += np.bincount(_cells(w, at, window), minlength=CELLS + 1)
                size += len(w.data)
        if size:
            total[CELLS] = size
            yield pa.RecordBatch.from_arrays([pa.array(np.arange(CELLS + 1, dtype=np.int32)), pa.array(total)], ["cell", "n"])

    out = np.zeros(CELLS + 1, np.int64)
    for cell, n in docs.select(F.col("text").cast("string")).mapInArrow(T.tidy(count), "cell int, n long").groupBy("cell").agg(F.sum("n")).collect():  # CELLS + 1 rows at most
        out[cell] = n
    return out[:CELLS], int(out[CELLS])


def _cells(w: T.Words, at: np.ndarray, window: int) -> np.ndarray:
    """Cell of the prefix of the window at each of the words ``at``."""
    p, first = T.windows(w, min(PREFIX, window))
    return (p[np.searchsorted(first, at)] & np.uint64(CELLS - 1)).astype(np.int64)


def deal(counts: np.ndarray, budget: int, least: int) -> tuple[np.ndarray, np.ndarray, int]:
    """(first group, number of groups) of each cell, and the number of groups; more than one group: extended prefixes."""
    budget = max(1, min(budget, int(counts.sum()) // least + 1))
    first, width = np.zeros(len(counts), np.int64), np.ones(len(counts), np.int64)
    group, filled = 0, 0
    for c in np.argsort(-counts, kind="stable"):
        if counts[c] > budget:
            first[c], width[c] = group, -(-int(counts[c]) // budget)
            group += int(width[c])
            continue
        if filled + counts[c] > budget:
            group, filled = group + 1, 0
        first[c] = group
        filled += counts[c]
    return first, width, group + 1


def laid_out(docs: DataFrame, parts: int, carry: tuple[str, ...] = (), part_bytes: int = PART_BYTES) -> DataFrame:
    """(part, doc_id, text, carried columns): equal texts share a part, so their paths are sent once; a text whose copies alone would fill
    half a part is spread over several parts by its ids."""
    doc_id, text = F.col("doc_id").cast("long"), F.col("text").cast("string")
    by = F.coalesce(F.xxhash64(text), F.lit(0))
    rows = docs.select(by.alias("__by"), doc_id.alias("doc_id"), text.alias("text"), *(F.col(c).alias(f"__{i}") for i, c in enumerate(carry)))
    weight = F.sum(F.coalesce(F.octet_length("text"), F.lit(0)) + 64)
    hot = rows.groupBy("__by").agg(weight.alias("weight")).where(F.col("weight") > part_bytes // 2)
    hot = cut(hot.select(F.col("__by").alias("__hot"), F.ceil(F.col("weight") / (part_bytes // 2)).alias("spread")))  # at most two for each part's bytes
    hot = F.broadcast(hot) if hot.count() <= BROADCAST_ROWS else hot
    rows = rows.join(hot, F.col("__by") == F.col("__hot"), "left")
    own = F.when(F.col("spread").isNull(), F.lit(0)).otherwise(F.pmod(F.xxhash64("doc_id"), F.col("spread")))
    return rows.select(F.pmod(F.col("__by") + own, F.lit(parts)).cast("int").alias("part"), "doc_id", "text", *(f"__{i}" for i in range(len(carry))))


def _squeeze(gaps: np.ndarray) -> bytes:
    """Non-negative numbers, byte plane by byte plane, compressed."""
    x = gaps.astype("<u8")
    planes = max(1, -(-int(x.max()).bit_length() // 8)) if len(x) else 1
    return bytes([planes]) + zstandard.compress(np.ascontiguousarray(x.view(np.uint8).reshape(-1, 8)[:, :planes].T).tobytes(), 1)


def _unsqueeze(raw: bytes) -> np.ndarray:
    planes = np.frombuffer(zstandard.decompress(raw[1:]), np.uint8).reshape(raw[0], -1)
    out = np.zeros((planes.shape[1], 8), np.uint8)
    out[:, : raw[0]] = planes.T
    return out.view("<i8").ravel()


def _gaps(numbers: np.ndarray) -> np.ndarray:
    """First number and steps of a sorted array; ids may be negative."""
    return np.diff(numbers.astype(np.int64), prepend=np.int64(0)) if len(numbers) else numbers


class PartWindows:
    """Windows of the documents of a part that have an id, its rows ordered by id and text: word index, 64-bit label and document id of each."""

    def __init__(self, table: pa.Table, window: int) -> None:
        table = table.take(pc.sort_indices(table, [("doc_id", "ascending"), ("text", "ascending")]))
        self.table = table
        texts = table.column("text").combine_chunks() if table.num_rows else pa.array([], pa.string())
        ids = table.column("doc_id").combine_chunks()
        self.w = T.words(texts)
        h, at = T.windows(self.w, window)
        doc = np.searchsorted(self.w.first, at, side="right") - 1
        has = ids.is_valid().to_numpy(zero_copy_only=False)[doc]
        self.label, self.at = h[has], at[has]
        self.own = ids.fill_null(0).to_numpy(zero_copy_only=False)[doc[has]]

    def shared(self) -> tuple[np.ndarray, np.ndarray]:
        """Sorted labels, and whether more than one document of the part has each."""
        order = np.lexsort((self.own, self.label))
        h, own = self.label[order], self.own[order]
        at = np.flatnonzero(_runs(h))
        last = np.append(at[1:], len(h)) - 1 if len(at) else at
        return h[at], own[at] != own[last]

    def printed(self, groups: int) -> tuple[np.ndarray, np.ndarray, np.ndarray, np.ndarray, np.ndarray]:
        """Sorted labels, whether the part alone makes them shared, and of the others the index, group and print, in order of the last two."""
        h, sure = self.shared()
        to = (h % np.uint64(groups)).astype(np.int64)
        mark = ((h >> np.uint64(32)) & np.uint64((1 << PRINT_BITS) - 1)).astype(np.int64)
        order = np.lexsort((mark, to))
        return h, sure, order, to[order], mark[order]

    def paths(self, keep: np.ndarray, window: int) -> Paths:
        """The windows of this mask, sorted by label and document, and the words on their paths."""
        i = np.flatnonzero(keep)
        i = i[np.lexsort((self.own[i], self.label[i]))]
        used, path = np.unique(self.at[i][:, None] + np.arange(window), return_inverse=True)
        words = _words_of(self.w, used).dictionary_encode()
        path = words.indices.to_numpy(zero_copy_only=False)[path.reshape(-1, window)]
        new = _runs(self.label[i])
        new[1:] |= (path[1:] != path[:-1]).any(axis=1)  # one label, other words: a path of its own
        low = self.own[i][new][np.cumsum(new) - 1] if len(i) else self.own[i]
        return Paths(i, path, words.dictionary, new, low)


@dataclass
class Paths:
    """Windows in path order: index, word codes, the dictionary, first of each path, smallest document on the path."""

    index: np.ndarray
    codes: np.ndarray
    words: pa.Array
    new: np.ndarray
    low: np.ndarray


def _words_of(w: T.Words, at: np.ndarray) -> pa.Array:
    """The words at these indices, as one binary array."""
    lengths = w.ends[at] - w.starts[at]
    offsets = np.concatenate([[0], np.cumsum(lengths)])
    source = np.arange(offsets[-1]) + np.repeat(w.starts[at] - offsets[:-1], lengths)
    return pa.LargeBinaryArray.from_buffers(pa.large_binary(), len(at), [None, pa.py_buffer(offsets.astype(np.int64).tobytes()), pa.py_buffer(w.data[source].tobytes())])


def _blob(words: pa.Array) -> tuple[bytes, bytes]:
    """Lengths and bytes of a freshly taken binary array."""
    _, offsets, data = words.buffers()
    off = np.frombuffer(offsets, np.int64)[words.offset : words.offset + len(words) + 1]
    return np.diff(off).astype(np.uint32).tobytes(), data.to_pybytes()[off[0] : off[-1]] if data is not None else b""


def _unblob(lengths: bytes, data: bytes) -> pa.Array:
    off = np.concatenate([[0], np.cumsum(np.frombuffer(lengths, np.uint32).astype(np.int64))])
    return pa.LargeBinaryArray.from_buffers(pa.large_binary(), len(off) - 1, [None, pa.py_buffer(off.tobytes()), pa.py_buffer(data)])


SENT = "key int, part int, n int, low long, ids binary, places binary, codes binary, lengths binary, words binary"


def prints(laid: DataFrame, window: int, groups: int) -> DataFrame:
    """(part, to, bits): for each part and group of prints, which of the part's prints some other part has."""
    tasks = min(groups, MOST_TASKS)
    key_of = T.even_keys(tasks).astype(np.int32)

    def send(table: pa.Table) -> pa.Table:
        part = table.column("part")[0].as_py()
        _, sure, order, to, mark = PartWindows(table, window).printed(groups)
        sure = sure[order]
        rows = []
        for g, (a, b) in zip(*_spans(to), strict=True):
            rows.append((int(key_of[g % tasks]), int(g), part, *(_squeeze(_gaps(mark[a:b][m])) for m in (~sure[a:b], sure[a:b]))))
        columns = list(zip(*rows, strict=True)) or [()] * 5
        T.release()
        return pa.Table.from_arrays([pa.array(c, k) for c, k in zip(columns, (pa.int32(), pa.int32(), pa.int32(), pa.binary(), pa.binary()), strict=True)], ["key", "to", "part", "one", "many"])

    def meet(batches):
        who, one, many = [], [], []
        for batch in batches:
            for to, part, x, y in zip(*(batch.column(c).to_pylist() for c in ("to", "part", "one", "many")), strict=True):
                who.append((part, to))
                one.append(np.cumsum(_unsqueeze(x)) | to << PRINT_BITS)
                many.append(np.cumsum(_unsqueeze(y)) | to << PRINT_BITS)
        if not who:
            return
        key, sure = np.concatenate(one), np.unique(np.concatenate(many))
        order = np.argsort(key, kind="stable")
        new = _runs(key[order])
        again = ~new
        again[:-1] |= ~new[1:]
        met = np.zeros(len(key), bool)
        met[order] = again
        if len(sure) and len(key):
            met |= sure[np.minimum(np.searchsorted(sure, key), len(sure) - 1)] == key
        ends = np.cumsum([len(x) for x in one])
        rows = [(part, to, np.packbits(met[b - len(x) : b]).tobytes()) for (part, to), x, b in zip(who, one, ends, strict=True)]
        yield pa.RecordBatch.from_arrays([pa.array(c, k) for c, k in zip(zip(*rows, strict=True), (pa.int32(), pa.int32(), pa.binary()), strict=True)], ["part", "to", "bits"])

    sent = laid.groupBy("part").applyInArrow(send, "key int, to int, part int, one binary, many binary")
    return sent.repartition(tasks, "key").mapInArrow(T.tidy(meet), "part int, to int, bits binary")


def repeated_windows(laid: DataFrame, window: int, counts: np.ndarray, budget: int = GROUP_WINDOWS, least: int = 32) -> DataFrame:
    """(part, places): packed word places, in the part's order, at which a window starts that starts in a smaller document of another part."""
    first, width, groups = deal(counts, budget, least)
    print_groups = max(LEAST_PARTS, int(counts.sum()) // PRINT_GROUP)
    key_of = T.even_keys(groups).astype(np.int32)
    kinds = (pa.int32(), pa.int32(), pa.int32(), pa.int64(), *[pa.binary()] * 5)

    def send(key, left: pa.Table, right: pa.Table) -> pa.Table:
        rows = []
        if left.num_rows:
            windows = PartWindows(left, window)
            h, sure, order, to, _ = windows.printed(print_groups)
            lone = order[~sure[order]]
            to = to[~sure[order]]
            for g, bits in zip(right.column("to").to_pylist(), right.column("bits").to_pylist(), strict=True):
                a, b = np.searchsorted(to, (g, g + 1))
                sure[lone[a:b]] = np.unpackbits(np.frombuffer(bits, np.uint8), count=b - a).astype(bool)
            if sure.any():
                rows = packs(left.column("part")[0].as_py(), windows, windows.paths(sure[np.searchsorted(h, windows.label)], window))
        columns = list(zip(*rows, strict=True)) or [()] * len(kinds)
        T.release()
        return pa.Table.from_arrays([pa.array(c, k) for c, k in zip(columns, kinds, strict=True)], [c.split()[0] for c in SENT.split(", ")])

    def packs(part: int, windows: PartWindows, p: Paths) -> list[tuple]:
        """A path of the part once, by group."""
        i, path = p.index[p.new], p.codes[p.new]
        order = np.argsort(windows.at[i], kind="stable")  # by place, which is by document too
        i, path = i[order], path[order]
        at, own = windows.at[i], windows.own[i]
        cell = _cells(windows.w, at, window)
        group = first[cell] + (windows.label[i] >> np.uint64(20)).astype(np.int64) % width[cell]
        order = np.argsort(group, kind="stable")
        rows = []
        for g, (x, y) in zip(*_spans(group[order]), strict=True):
            mine = order[x:y]
            codes, local, often = np.unique(path[mine], return_inverse=True, return_counts=True)
            by = np.argsort(-often, kind="stable")  # frequent words get small codes
            rank = np.empty(len(by), np.int64)
            rank[by] = np.arange(len(by))
            low = int(own[mine[0]])
            rows.append((int(key_of[g % groups]), part, len(mine), low, _squeeze(_gaps(own[mine] - low)), _squeeze(_gaps(at[mine])), _squeeze(rank[local.ravel()]), *map(zstandard.compress, _blob(p.words.take(pa.array(codes[by]))))))
        return rows

    def subtree(batches):
        mine = [tuple(r.values()) for batch in batches for r in batch.select(["part", "n", "low", "ids", "places", "codes", "lengths", "words"]).to_pylist()]
        if not mine:
            return
        blobs = [_unblob(zstandard.decompress(r[6]), zstandard.decompress(r[7])) for r in mine]
        words = pa.concat_arrays(blobs).dictionary_encode()
        rank = np.empty(len(words.dictionary), np.int32)
        rank[pc.sort_indices(words.dictionary).to_numpy()] = np.arange(len(rank), dtype=np.int32)
        symbol = rank[words.indices.to_numpy(zero_copy_only=False)]
        at, paths = 0, []
        for r, blob in zip(mine, blobs, strict=True):
            paths.append(symbol[_unsqueeze(r[5]) + at].reshape(-1, window))  # 4 bytes a word
            at += len(blob)
        path = np.concatenate(paths)
        own = np.concatenate([np.cumsum(_unsqueeze(r[3])) + r[2] for r in mine])
        place = np.concatenate([np.cumsum(_unsqueeze(r[4])) for r in mine])
        part = np.repeat(np.array([r[0] for r in mine]), [r[1] for r in mine])
        mine.clear()
        paths.clear()
        order = np.lexsort((own, *path.T[::-1]))  # suffixes by words, of equal ones the smallest document first
        path, own, place, part = path[order], own[order], place[order], part[order]
        common = np.zeros(len(path), np.int64)  # words that a suffix shares with the one before
        common[1:] = np.logical_and.accumulate(path[1:] == path[:-1], axis=1).sum(axis=1)
        node = np.cumsum(common < window) - 1  # leaves of one node at the window's depth or below
        later = own > own[common < window][node]
        place, part = place[later], part[later]
        order = np.lexsort((place, part))
        rows = [(int(p), _squeeze(_gaps(place[order[x:y]]))) for p, (x, y) in zip(*_spans(part[order]), strict=True)]
        if rows:
            yield pa.RecordBatch.from_arrays([pa.array(c, k) for c, k in zip(zip(*rows, strict=True), (pa.int32(), pa.binary()), strict=True)], ["part", "places"])

    met = prints(laid, window, print_groups)
    sent = laid.groupBy("part").cogroup(met.groupBy("part")).applyInArrow(send, SENT)
    return sent.repartition(groups, "key").mapInArrow(T.tidy(subtree), "part int, places binary")


def remove_repeats(docs: DataFrame, window: int = 13, cutter: Callable | None = None, columns: str = "n_words long, n_removed long, kept string", carry: tuple[str, ...] = ()) -> DataFrame:
    """Every row of ``docs(doc_id, text)`` with what is left of it: doc_id, n_words, n_removed, kept, or what ``cutter`` makes.

    Columns named in ``carry`` come along after doc_id.

    A word goes if it lies in a window of ``window`` consecutive words that also starts in a document with a smaller doc_id,
    judged on the input.  Kept words are joined by one space.  Null, empty and blank texts have no words and stay
    empty; texts shorter than the window keep all words; rows with a null doc_id neither lose words nor cost others
    theirs; rows that share a doc_id don't count as earlier than each other.  An empty table gives an empty one.
    cutter(words, keep mask) returns the values of ``columns`` for one text.
    """
    docs = T.bounded(docs)
    counts, size = prefix_counts(docs, window)
    parts = max(LEAST_PARTS, size // PART_BYTES)
    laid = laid_out(docs, parts, carry)
    found = repeated_windows(laid, window, counts)
    cutter = cutter or kept_text
    names = [c.split()[0] for c in columns.split(", ")]
    carried = docs.select(*carry).schema.fields
    schema = ", ".join(["doc_id long", *(f"`{f.name}` {f.dataType.simpleString()}" for f in carried), columns])

    def cut_out(key, left: pa.Table, right: pa.Table) -> pa.Table:
        windows = PartWindows(left, window)
        left = windows.table
        told = np.concatenate([np.zeros(0, np.int64), *(np.cumsum(_unsqueeze(x)) for x in right.column("places").to_pylist())])
        told = np.searchsorted(windows.at, told)
        pair = T.mix(windows.own.view(np.uint64)) ^ windows.label
        gone = np.isin(pair, pair[told])  # wherever the document has that window
        h, sure = windows.shared()
        if sure.any():
            p = windows.paths(sure[np.searchsorted(h, windows.label)], window)
            gone[p.index[windows.own[p.index] > p.low]] = True
        w = windows.w
        cover = np.zeros(len(w.hashes) + 1, np.int64)
        cover[windows.at[gone]] += 1
        np.subtract.at(cover, windows.at[gone] + window, 1)
        keep = np.cumsum(cover)[:-1] == 0
        columns_of = list(zip(*(cutter(w, x, y, keep[x:y]) for x, y in zip(w.first[:-1], w.first[1:], strict=True)), strict=True)) or [[] for _ in names]
        kinds = {"long": pa.int64(), "string": pa.string()}
        cols = [pa.array(v, kinds[c.split()[1]]) for v, c in zip(columns_of, columns.split(", "), strict=True)]
        T.release()
        return pa.Table.from_arrays([left.column("doc_id"), *(left.column(f"__{i}") for i in range(len(carry))), *cols], ["doc_id", *carry, *names])

    return laid.groupBy("part").cogroup(found.groupBy("part")).applyInArrow(cut_out, schema)


def _kept(w: T.Words, x: int, y: int, keep: np.ndarray) -> bytes:
    """Bytes of the kept words, joined by one space."""
    at = np.flatnonzero(keep) + x
    if not len(at):
        return b""
    lengths = w.ends[at] - w.starts[at]
    total = int(lengths.sum()) + len(at)
    ends = np.cumsum(lengths + 1)
    source = np.arange(total) + np.repeat(w.starts[at] - (ends - lengths - 1), lengths + 1)
    out = w.data[np.minimum(source, len(w.data) - 1)].copy()
    out[ends - 1] = 32
    return out[:-1].tobytes()


def kept_text(w: T.Words, x: int, y: int, keep: np.ndarray) -> tuple:
    return int(y - x), int(len(keep) - keep.sum()), _kept(w, x, y, keep).decode()


def kept_or_whole(w: T.Words, x: int, y: int, keep: np.ndarray) -> tuple:
    """The kept words where any went; None where the text stays as it is."""
    return (None if keep.all() else _kept(w, x, y, keep).decode(),)


def kept_digest(w: T.Words, x: int, y: int, keep: np.ndarray) -> tuple:
    return int(y - x), int(len(keep) - keep.sum()), hashlib.sha256(_kept(w, x, y, keep)).hexdigest()
