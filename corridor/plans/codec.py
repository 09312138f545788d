"""Storing and reading tracks: wire order, chunks, blocks, and the way back.

A block of a bucket is read by itself.  It starts with a key frame, one packed grid value for each series present, then has chunks of
pieces in wire order without series ids.  Wire order is (start, series): the reader, who knows when each series' present piece ends,
replays the same order from a heap and so knows whose piece comes next.
"""

from __future__ import annotations

import heapq
import struct

import numpy as np
import pyarrow as pa
import pyarrow.compute  # noqa: F401
from pyspark.sql import DataFrame, Window
from pyspark.sql import functions as F

from corridor.functions import vwidth
from corridor.operators.segment import cut_blocks, matrix, scan_matrix
from corridor.options import Options

STORED = "block long, bucket int, seq int, n int, payload binary, header binary"
KEY_FRAME = -1


def wire_order(pieces: DataFrame, o: Options) -> DataFrame:
    """Pieces with bucket, their place in the bucket's stream and the chunk they go to; a sort, no queue."""
    rows = pieces.withColumn("bucket", F.floor(F.col("k") / o.width).cast("int"))
    place = F.row_number().over(Window.partitionBy("block", "bucket").orderBy("t0", "k")) - 1
    return rows.withColumn("place", place).withColumn("seq", F.floor(F.col("place") / o.chunk).cast("int"))


def chunk_numbers(pieces: DataFrame, o: Options) -> DataFrame:
    """(block, bucket, seq, n, numbers): the whole numbers of each chunk in stored order, signs mapped."""
    from corridor.functions.quant import zigzag

    rows = wire_order(pieces, o).select("block", "bucket", "seq", "place", zigzag(F.col("dq"), o.zigzag).alias("u"), (F.col("dt") - 1).cast("long").alias("d"))
    lists = rows.groupBy("block", "bucket", "seq").agg(F.count("*").cast("int").alias("n"), F.array_sort(F.collect_list(F.struct("place", "u", "d"))).alias("s"))  # a chunk long
    u, d = F.transform("s", lambda r: r["u"]), F.transform("s", lambda r: r["d"])
    numbers = {"split": F.concat(F.reverse(u), d), "forward": F.concat(u, d), "interleaved": F.flatten(F.transform("s", lambda r: F.array(r["u"], r["d"])))}[o.layout]
    return lists.select("block", "bucket", "seq", "n", numbers.alias("numbers"))


def pack_chunk(dq: np.ndarray, dt: np.ndarray, o: Options) -> np.ndarray:
    u, d = vwidth.zigzag(dq, o.zigzag), (dt - 1).astype(np.uint64)
    if o.layout == "interleaved":
        return np.stack([u, d], axis=1).ravel()
    return np.concatenate([u[::-1] if o.layout == "split" else u, d])


def unpack_chunk(numbers: np.ndarray, o: Options) -> tuple[np.ndarray, np.ndarray]:
    n = len(numbers) // 2
    if o.layout == "interleaved":
        u, d = numbers[::2], numbers[1::2]
    else:
        u, d = numbers[:n], numbers[n:]
        u = u[::-1] if o.layout == "split" else u
    return vwidth.unzigzag(u, o.zigzag), d.astype(np.int64) + 1


def key_frame_bytes(ids: np.ndarray, t0: np.ndarray, length: np.ndarray, q: np.ndarray) -> tuple[bytes, bytes]:
    """(packed grid values, header): the width is that of the values' span; the header tells the series, their first steps and lengths.

    ids must ascend.  Where all series of a run are present for the whole block, a run of 64 costs 30 bits of header.
    """
    low = int(q.min())
    width = int(q.max() - low).bit_length()
    start, longest = int(t0.min()), int(length.max())
    rest = np.concatenate([np.diff(ids) - 1, t0 - start, longest - length]).astype(np.uint64)
    return vwidth.pack_fixed((q - low).astype(np.uint64), width), _HEAD.pack(low, width, len(ids), int(ids[0]), start, longest) + vwidth.encode(rest)


_HEAD = struct.Struct("<qBIqqI")


def read_key_frame(payload: bytes, header: bytes):
    low, width, n, first, start, longest = _HEAD.unpack_from(header)
    rest = vwidth.decode(header[_HEAD.size :], 3 * n - 1).astype(np.int64)
    ids = first + np.concatenate([[0], np.cumsum(rest[: n - 1] + 1)]).astype(np.int64)
    return ids, rest[n - 1 : 2 * n - 1] + start, longest - rest[2 * n - 1 :], vwidth.unpack_fixed(payload, n, width).astype(np.int64) + low


def store_block(block: int, bucket: int, ids, t0, length, y, o: Options) -> list[tuple]:
    k, s, dt, _, dq = scan_matrix(y, length, t0, o)
    frame, header = key_frame_bytes(ids, t0, length, np.floor(y[0] + 0.5).astype(np.int64))
    rows = [(block, bucket, KEY_FRAME, len(ids), frame, header)]
    order = np.lexsort((k, s))
    dt, dq = dt[order], dq[order]
    return rows + [(block, bucket, seq, n, payload, b"") for seq, (n, payload) in enumerate(chunk_codes(dq, dt, o))]


def chunk_codes(dq: np.ndarray, dt: np.ndarray, o: Options) -> list[tuple[int, bytes]]:
    """(pieces, code) of each chunk of pieces in stored order."""
    parts = [slice(a, a + o.chunk) for a in range(0, len(dt), o.chunk)]
    return [(len(dt[p]), code) for p, code in zip(parts, vwidth.encode_many([pack_chunk(dq[p], dt[p], o) for p in parts]), strict=True)]


_TYPES = [pa.int64(), pa.int32(), pa.int32(), pa.int32(), pa.binary(), pa.binary()]
_NAMES = ["block", "bucket", "seq", "n", "payload", "header"]


def _table(rows: list[tuple]) -> pa.Table:
    columns = list(zip(*rows, strict=True)) if rows else [[] for _ in _NAMES]
    return pa.table([pa.array(c, t) for c, t in zip(columns, _TYPES, strict=True)], names=_NAMES)


def compress(track: DataFrame, o: Options, fused: bool = True) -> DataFrame:
    """Stored rows ``(block, bucket, seq, n, payload, header)`` of a connected track.

    Fused: one Python stage scans, orders, packs and codes a block of a bucket.  Otherwise pieces become rows first, and chunks are made
    from those; the bytes are the same.
    """
    if not o.connect:
        raise ValueError("the stored form is of connected pieces")
    cut = cut_blocks(track, o)

    def whole(table: pa.Table) -> pa.Table:
        block, bucket = table.column("block")[0].as_py(), table.column("bucket")[0].as_py()
        return _table(store_block(block, bucket, *matrix(*(np.asarray(table.column(c)) for c in ("k", "t", "y"))), o))

    if fused:
        return cut.groupBy("block", "bucket").applyInArrow(whole, STORED)
    from corridor.operators.segment import vector_scan

    def code(batches):
        for b in batches:
            rows = [(r["block"], r["bucket"], r["seq"], r["n"], vwidth.encode(np.array(r["numbers"], np.uint64)), b"") for r in b.to_pylist()]
            yield from _table(rows).to_batches()

    def frame(table: pa.Table) -> pa.Table:
        block, bucket = table.column("block")[0].as_py(), table.column("bucket")[0].as_py()
        ids, t0, length, q = (np.asarray(table.sort_by("k").column(c)) for c in ("k", "t", "n", "q"))
        return _table([(block, bucket, KEY_FRAME, len(ids), *key_frame_bytes(ids, t0, length, q))])

    first = cut.groupBy("block", "bucket", "k").agg(F.min("t").alias("t"), F.count("*").alias("n"), F.min_by("y", "t").alias("y"))
    first = first.select("block", "bucket", "k", "t", "n", F.floor(F.col("y") + 0.5).cast("long").alias("q"))
    frames = first.groupBy("block", "bucket").applyInArrow(frame, STORED)
    return frames.union(chunk_numbers(vector_scan(track, o), o).mapInArrow(code, STORED))


def pack_parts(parts: DataFrame, columns: list[str]) -> DataFrame:
    """One row for each ``part``, its whole-number columns packed."""

    def run(table: pa.Table) -> pa.Table:
        return pa.table([table.column("part").slice(0, 1), *(pa.array([_ints(np.asarray(table.column(c)))], pa.binary()) for c in columns)], names=["part", *columns])

    return parts.groupBy("part").applyInArrow(run, ", ".join(["part long", *(f"{c} binary" for c in columns)]))


def part_blocks(batch: pa.RecordBatch, fill, o: Options):
    """(block, bucket, ids, t0, length, y) of the blocks of packed parts that hold whole buckets; ``fill`` as for ``compress_spread``."""
    for i in range(len(batch)):
        row = pa.Table.from_batches([batch.slice(i, 1)]).drop_columns(["part"])
        ids, length, x = fill(pa.table({c: unpack_ints(row.column(c).to_pylist()) for c in row.column_names}))
        of = ids // o.width
        for bucket in np.unique(of).tolist():
            for block in range(-(-int(length[of == bucket].max()) // o.block)):
                at = np.flatnonzero((of == bucket) & (length > block * o.block))
                left = np.minimum(length[at] - block * o.block, o.block)
                y = x[block * o.block : block * o.block + int(left.max()), at] / o.grid
                yield block, bucket, ids[at], np.full(len(at), block * o.block), left, y


def compress_parts(parts: DataFrame, fill, o: Options) -> DataFrame:
    """The rows that ``compress`` stores, from packed parts that hold whole buckets; nothing is shuffled."""

    def run(batches):
        for batch in batches:
            for block in part_blocks(batch, fill, o):
                yield from _table(store_block(*block, o)).to_batches()

    return parts.mapInArrow(run, STORED)


PARTS = STORED + ", slot long, whole boolean"
SLOT_STEPS, SEQS = 32, 256


def _ints(a: np.ndarray) -> bytes:
    """Whole numbers from their least, in as few bytes each as all fit."""
    low = int(a.min())
    u = (a - low).astype(np.uint64)
    size = next(b for b in (1, 2, 4, 8) if int(u.max()) < 1 << 8 * b)
    return struct.pack("<qB", low, size) + u.astype(f"<u{size}").tobytes()


def unpack_ints(rows: list[bytes]) -> np.ndarray:
    """The numbers of some rows, one after the other."""
    out = []
    for raw in rows:
        low, size = struct.unpack_from("<qB", raw)
        out.append(np.frombuffer(raw, f"<u{size}", offset=9).astype(np.int64) + low)
    return np.concatenate(out)


def compress_spread(parts: DataFrame, fill, o: Options) -> DataFrame:
    """The rows that ``compress`` stores of tracks of one block, where many tasks work at one bucket; writes to the checkpoint folder.

    ``fill(table)`` makes (ids, length, steps x series matrix) of the rows with one ``part``; all series of an id lie in one part.  Scans run by
    part; their pieces, packed, are then dealt by bucket and a slot of start times.  A slot's pieces have consecutive places in the bucket's stream, so
    its task codes all chunks that lie in it, and chunks across slots are put together at the end.
    """
    from corridor.runtime import cut

    tasks = 4 * parts.sparkSession.sparkContext.defaultParallelism  # few bytes, much work: never merged into one task

    def scan(table: pa.Table) -> pa.Table:
        ids, length, x = fill(table)
        if len(x) > o.block:
            raise ValueError("a series is longer than a block")
        k, s, dt, _, dq = scan_matrix(x / o.grid, length, np.zeros(len(ids), np.int64), o)
        first, bucket = np.floor(x[0] / o.grid + 0.5).astype(np.int64), ids // o.width
        rows = [(int(b), KEY_FRAME, int(np.count_nonzero(bucket == b)), *(_ints(c[bucket == b]) for c in (ids, length, first)), b"") for b in np.unique(bucket)]
        place = bucket[k] * (o.block // SLOT_STEPS + 1) + s // SLOT_STEPS
        order = np.argsort(place, kind="stable")
        ends = np.flatnonzero(np.diff(place[order], append=-1)) + 1
        for at in np.split(order, ends[:-1]) if len(order) else []:
            rows.append((int(bucket[k[at[0]]]), int(s[at[0]]) // SLOT_STEPS, len(at), *(_ints(c[at]) for c in (ids[k], s, dt, dq))))
        types = (pa.int32(), pa.int64(), pa.int64(), *[pa.binary()] * 4)
        return pa.table([pa.array(c, t) for c, t in zip(zip(*rows, strict=True), types, strict=True)], names=["bucket", "slot", "pieces", "c0", "c1", "c2", "c3"])

    scanned = cut(parts.groupBy("part").applyInArrow(scan, "bucket int, slot long, pieces long, c0 binary, c1 binary, c2 binary, c3 binary"))
    before = F.sum("pieces").over(Window.partitionBy("bucket").orderBy("slot"))
    starts = scanned.where(F.col("slot") != KEY_FRAME).groupBy("bucket", "slot").agg(F.sum("pieces").alias("pieces"))
    starts = starts.select("bucket", "slot", (before - F.col("pieces")).alias("start"))  # a row for each bucket and slot

    def code(table: pa.Table) -> pa.Table:
        bucket, slot, start = (table.column(c)[0].as_py() for c in ("bucket", "slot", "start"))
        columns = [unpack_ints(table.column(c).to_pylist()) for c in (("c0", "c1", "c2") if slot == KEY_FRAME else ("c0", "c1", "c2", "c3"))]
        if slot == KEY_FRAME:
            order = np.argsort(columns[0])
            ids, length, first = (c[order] for c in columns)
            rows = [(0, bucket, KEY_FRAME, len(ids), *key_frame_bytes(ids, np.zeros(len(ids), np.int64), length, first), slot, True)]
        else:
            k, s, dt, dq = columns
            order = np.lexsort((k, s))
            dt, dq = dt[order], dq[order]
            head, seq = min(-start % o.chunk, len(dt)), -(-start // o.chunk)
            full = (len(dt) - head) // o.chunk
            middle, tail = slice(head, head + full * o.chunk), slice(head + full * o.chunk, None)
            rows = [(0, bucket, seq + i, n, payload, b"", slot, True) for i, (n, payload) in enumerate(chunk_codes(dq[middle], dt[middle], o))]
            for at, part in ((seq - 1, slice(0, head)), (seq + full, tail)):
                if len(dt[part]):
                    rows.append((0, bucket, at, len(dt[part]), _ints(dq[part]), _ints(dt[part]), slot, False))
        types = (*_TYPES, pa.int64(), pa.bool_())
        return pa.table([pa.array(c, t) for c, t in zip(zip(*rows, strict=True), types, strict=True)], names=[*_NAMES, "slot", "whole"])

    def mend(table: pa.Table) -> pa.Table:
        whole = table.filter(table.column("whole")).select(_NAMES)
        cut_up = table.filter(pa.compute.invert(table.column("whole"))).sort_by([("seq", "ascending"), ("slot", "ascending")])
        seqs, at = np.unique(np.asarray(cut_up.column("seq")), return_index=True)
        rows = []
        for seq, a, b in zip(seqs.tolist(), at.tolist(), [*at.tolist()[1:], len(cut_up)], strict=False):  # none where no chunk was cut
            part = cut_up.slice(a, b - a)
            dq, dt = unpack_ints(part.column("payload").to_pylist()), unpack_ints(part.column("header").to_pylist())
            rows.append((0, part.column("bucket")[0].as_py(), seq, len(dq), vwidth.encode(pack_chunk(dq, dt, o)), b""))
        return pa.concat_tables([whole, _table(rows)])

    placed = scanned.join(F.broadcast(starts), ["bucket", "slot"], "left")
    coded = placed.repartition(tasks, "bucket", "slot").groupBy("bucket", "slot").applyInArrow(code, PARTS)
    return coded.repartition(tasks, "bucket", F.floor(F.col("seq") / SEQS)).groupBy("bucket", F.floor(F.col("seq") / SEQS)).applyInArrow(mend, STORED)


def stored_bits(rows: list[tuple]) -> int:
    """Bits of a block's stored rows, as ``packed_bits`` counts them."""
    return 8 * sum(len(payload) + len(header) + (0 if seq == KEY_FRAME else 4) for _, _, seq, _, payload, header in rows)


def read_block(table: pa.Table, o: Options):
    """Pieces of one block of a bucket: (series, t0, dt, p0, dq), and its key frame; replays the writer's order from a heap."""
    rows = sorted(table.to_pylist(), key=lambda r: r["seq"])
    ids, t0, length, q = read_key_frame(rows[0]["payload"], rows[0]["header"])
    parts = [unpack_chunk(vwidth.decode(r["payload"], 2 * r["n"]), o) for r in rows[1:]]
    dq = np.concatenate([p[0] for p in parts]).tolist() if parts else []
    dt = np.concatenate([p[1] for p in parts]).tolist() if parts else []
    last = (t0 + length - 1).tolist()
    at = q.tolist()
    heap = [(int(t), i) for i, t in enumerate(t0) if length[i] > 1]
    heapq.heapify(heap)
    out = []
    for d, v in zip(dt, dq, strict=True):
        t, i = heapq.heappop(heap)
        out.append((i, t, d, at[i], v))
        at[i] += v
        if t + d < last[i]:
            heapq.heappush(heap, (t + d, i))
    columns = [np.array(c, np.int64) for c in zip(*out, strict=True)] if out else [np.zeros(0, np.int64)] * 5
    return columns, (ids, t0, length, q)


def pieces_of(stored: DataFrame, o: Options) -> DataFrame:
    """Pieces ``(block, k, t0, dt, p0, dq)`` read from stored blocks."""

    def run(table: pa.Table) -> pa.Table:
        (i, t, d, p, v), (ids, *_) = read_block(table, o)
        return pa.table({"block": pa.array(np.full(len(i), table.column("block")[0].as_py(), np.int64)), "k": pa.array(ids[i]), "t0": pa.array(t), "dt": pa.array(d.astype(np.int32)), "p0": pa.array(p), "dq": pa.array(v)})

    return stored.groupBy("block", "bucket").applyInArrow(run, "block long, k long, t0 long, dt int, p0 long, dq long")


def decompress(stored: DataFrame, o: Options) -> DataFrame:
    """Samples ``(k, t, x)`` of stored blocks."""

    def run(table: pa.Table) -> pa.Table:
        (i, t, d, p, v), (ids, t0, _, q) = read_block(table, o)
        s = np.arange(int(d.sum())) - np.repeat(np.cumsum(d) - d, d) + 1
        piece = np.repeat(np.arange(len(d)), d)
        x = o.grid * (p[piece] + v[piece] * s / d[piece])
        k = np.concatenate([ids, ids[i[piece]]])
        return pa.table({"k": pa.array(k), "t": pa.array(np.concatenate([t0, t[piece] + s])), "x": pa.array(np.concatenate([q * o.grid, x]))})

    return stored.groupBy("block", "bucket").applyInArrow(run, "k long, t long, x double")


def queue_order(pieces: DataFrame, o: Options, dense: bool = False) -> DataFrame:
    """(block, k, t0, place) by the writer's queues: pieces arrive as scans close them and leave when none earlier can follow.

    dense: the waiting pieces lie in an array by start time, in place of a heap.
    """

    def run(table: pa.Table) -> pa.Table:
        k, t0, dt = (np.asarray(table.column(c)) for c in ("k", "t0", "dt"))
        arrival = np.lexsort((k, t0 + dt))
        ready: list = [[] for _ in range(int(t0.max() - t0.min()) + 1)] if dense else []
        base = int(t0.min())
        first: dict[int, int] = {}
        for a, b in zip(k.tolist(), t0.tolist(), strict=True):
            first[a] = min(b, first.get(a, b))
        final = {a: 0 for a in first}
        for a, b in zip(k.tolist(), (t0 + dt).tolist(), strict=True):
            final[a] = max(final[a], b)
        expected = [(t, a) for a, t in first.items()]
        heapq.heapify(expected)
        waiting: dict = {}
        out = []
        for j in arrival.tolist():
            a, t, d = int(k[j]), int(t0[j]), int(dt[j])
            if dense:
                ready[t - base].append(a)
            else:
                heapq.heappush(ready, (t, a))
            waiting[(t, a)] = d
            while expected and expected[0] in waiting:
                t, a = heapq.heappop(expected)
                out.append((a, t))
                d = waiting.pop((t, a))
                if t + d < final[a]:
                    heapq.heappush(expected, (t + d, a))
        return pa.table({"block": pa.array([table.column("block")[0].as_py()] * len(out), pa.int64()), "k": pa.array([a for a, _ in out], pa.int64()), "t0": pa.array([t for _, t in out], pa.int64()), "place": pa.array(range(len(out)), pa.int64())})

    rows = pieces.withColumn("bucket", F.floor(F.col("k") / o.width).cast("int"))
    return rows.groupBy("block", "bucket").applyInArrow(run, "block long, k long, t0 long, place long")


def packed_bits(stored: DataFrame) -> DataFrame:
    """One row: bytes of key frames, of their headers and of chunks, in bits, and their sum."""
    frame = F.col("seq") == KEY_FRAME
    bits = lambda c: F.coalesce(F.sum(c), F.lit(0)) * 8
    return stored.agg(
        bits(F.when(frame, F.octet_length("payload"))).alias("frame_bits"),
        bits(F.when(frame, F.octet_length("header"))).alias("header_bits"),
        bits(F.when(~frame, F.octet_length("payload") + 4)).alias("chunk_bits"),
        bits(F.octet_length("payload") + F.octet_length("header") + F.when(frame, 0).otherwise(4)).alias("packed_bits"),
    )
