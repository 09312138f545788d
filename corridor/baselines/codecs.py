"""Comparison codecs that need whole blocks: general compressors, transforms, adaptive coding, components, polynomials, simplification, covers."""

from __future__ import annotations

import bz2
import lzma
import zlib

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from corridor.functions.vwidth import bit_lengths, decode, encode, unzigzag, zigzag
from corridor.operators.segment import cut_blocks, matrix
from corridor.options import Options
from corridor.plans.codec import part_blocks

CODECS = {"bz2": (bz2.compress, bz2.decompress), "zlib": (zlib.compress, zlib.decompress), "lzma": (lzma.compress, lzma.decompress)}


def _blocks(track: DataFrame, o: Options, schema: str, make, fill=None) -> DataFrame:
    """``make(ids, t0, length, y)`` on each block of a bucket; rows of values for ``schema`` after block and bucket.

    fill: the track comes in parts of whole buckets, as ``codec.part_blocks`` reads them.
    """
    types = {"long": pa.int64(), "double": pa.float64(), "string": pa.string(), "boolean": pa.bool_(), "binary": pa.binary()}
    fields = [f.split() for f in schema.split(", ")]

    def of_parts(batches):
        for batch in batches:
            for block, bucket, *series in part_blocks(batch, fill, o):
                yield from stored(block, bucket, make(*series)).to_batches()

    def run(table: pa.Table) -> pa.Table:
        block, bucket = table.column("block")[0].as_py(), table.column("bucket")[0].as_py()
        return stored(block, bucket, make(*matrix(*(np.asarray(table.column(c)) for c in ("k", "t", "y")))))

    def stored(block: int, bucket: int, rows: list[tuple]) -> pa.Table:
        columns = list(zip(*rows, strict=True)) or [[] for _ in fields]
        return pa.table([pa.array([block] * len(rows), pa.int64()), pa.array([bucket] * len(rows), pa.int32()), *(pa.array(c, types[t]) for c, (_, t) in zip(columns, fields, strict=True))], names=["block", "bucket", *(n for n, _ in fields)])

    if fill is not None:
        return track.mapInArrow(of_parts, f"block long, bucket int, {schema}")
    tasks = 2 * track.sparkSession.sparkContext.defaultParallelism  # few bytes, much work: never merged into one task
    return cut_blocks(track, o).repartition(tasks, "block", "bucket").groupBy("block", "bucket").applyInArrow(run, f"block long, bucket int, {schema}")


def general(track: DataFrame, o: Options, names: tuple[str, ...] = tuple(CODECS), check: bool = True, fill=None) -> DataFrame:
    """Raw doubles of each block through general-purpose compressors: raw and packed bytes, and whether they came back (null unchecked)."""

    def make(ids, t0, length, y):
        raw = (y * o.grid).astype("<f8").tobytes()
        out = []
        for name in names:
            pack, unpack = CODECS[name]
            packed = pack(raw)
            out.append((name, len(raw), len(packed), unpack(packed) == raw if check else None))
        return out

    return _blocks(track, o, "codec string, raw_bytes long, packed_bytes long, lossless boolean", make, fill)


def bwt(data: bytes) -> tuple[bytes, int]:
    """Burrows-Wheeler transform: last column and the row of the original; rotations sorted by doubling."""
    n = len(data)
    if not n:
        return b"", 0
    raw = np.frombuffer(data, np.uint8)
    ahead, key = np.resize(raw, n + 8), np.zeros(n, np.uint64)
    for j in range(8):
        key = key << np.uint64(8) | ahead[j : n + j]
    order = np.argsort(key)
    rank, k = np.empty(n, np.int64), 8  # the place where those begin that are equal so far
    at, word = np.arange(n), key[order]
    while True:
        first = np.append(True, word[1:] != word[:-1])
        rank[order[at]] = np.maximum.accumulate(np.where(first, at, 0))
        at = at[~(first & np.append(first[1:], True))]  # only places of rotations that have an equal are sorted on
        if not len(at) or k >= n:
            break
        i = order[at]
        word = rank[i] * n + rank[(i + k) % n]
        by = np.argsort(word)
        order[at], word = i[by], word[by]
        k *= 2
    if len(at):  # equal rotations stand in the order of their starts
        order[at] = order[at][np.lexsort((order[at], rank[order[at]]))]
    return raw[(order - 1) % n].tobytes(), int(np.flatnonzero(order == 0)[0])


def unbwt(last: bytes, row: int) -> bytes:
    if not last:
        return b""
    col = np.frombuffer(last, np.uint8)
    nxt = np.argsort(col, kind="stable").tolist()
    first = np.sort(col).tolist()
    out, at = bytearray(), row
    for _ in range(len(last)):
        out.append(first[at])
        at = nxt[at]
    return bytes(out)


def front(data: bytes) -> bytes:
    """Move-to-front ranks."""
    raw = np.frombuffer(data, np.uint8)
    starts = np.flatnonzero(np.append(True, raw[1:] != raw[:-1])[: len(raw)])  # within a run all are 0
    table, ranks = list(range(256)), bytearray()
    for b in raw[starts].tolist():
        i = table.index(b)
        ranks.append(i)
        table.insert(0, table.pop(i))
    out = np.zeros(len(raw), np.uint8)
    out[starts] = np.frombuffer(ranks, np.uint8)
    return out.tobytes()


def unfront(data: bytes) -> bytes:
    table, out = list(range(256)), bytearray()
    for i in data:
        b = table.pop(i)
        out.append(b)
        table.insert(0, b)
    return bytes(out)


def varint(u: np.ndarray) -> bytes:
    """Seven bits a byte, low ones first."""
    u = np.asarray(u, np.uint64)
    n = np.maximum(1, -(-bit_lengths(u) // 7))
    at = np.arange(int(n.sum())) - np.repeat(np.cumsum(n) - n, n)
    v = (np.repeat(u, n) >> (at * 7).astype(np.uint64)) & np.uint64(127)
    more = at < np.repeat(n, n) - 1
    return (v | (more.astype(np.uint64) << np.uint64(7))).astype(np.uint8).tobytes()


def grid_deltas(y: np.ndarray, length: np.ndarray) -> np.ndarray:
    """Differences in time, then between neighbouring series, signs mapped; frame after frame."""
    q = np.floor(y + 0.5).astype(np.int64)
    d = np.diff(q, axis=0, prepend=0)
    r = np.diff(d, axis=1, prepend=0)
    return zigzag(r.ravel()[: int(length.max()) * y.shape[1]])


def native_stages(y: np.ndarray, length: np.ndarray) -> tuple[bytes, int, bytes]:
    """Differences byte-wise, the row of their transform, and the packed bytes."""
    raw = varint(grid_deltas(y, length))
    last, row = bwt(raw)
    return raw, row, zlib.compress(front(last), 9)


def native_full(track: DataFrame, o: Options, check: bool = True, fill=None) -> DataFrame:
    """Differences, byte-wise code, Burrows-Wheeler, move to front, Lempel-Ziv and Huffman."""

    def make(ids, t0, length, y):
        raw, row, packed = native_stages(y, length)
        return [(8 * int(length.sum()), len(raw), len(packed) + 8, unbwt(unfront(zlib.decompress(packed)), row) == raw if check else None)]

    return _blocks(track, o, "raw_bytes long, varint_bytes long, packed_bytes long, lossless boolean", make, fill)


class Counts:
    """Adaptive frequencies with a Fenwick tree."""

    def __init__(self, n: int) -> None:
        self.n, self.tree, self.total = n, [0] * (n + 1), 0
        for s in range(n):
            self.add(s, 1)

    def add(self, s: int, by: int) -> None:
        self.total += by
        s += 1
        while s <= self.n:
            self.tree[s] += by
            s += s & -s

    def below(self, s: int) -> int:
        out = 0
        while s:
            out += self.tree[s]
            s -= s & -s
        return out

    def find(self, v: int) -> int:
        at, step = 0, 1 << self.n.bit_length()
        while step:
            if at + step <= self.n and self.tree[at + step] <= v:
                at += step
                v -= self.tree[at]
            step >>= 1
        return at


LIMIT = 1 << 16
TOP, BOTTOM = 1 << 32, 1 << 24


def range_encode(symbols: list[int], n: int) -> bytes:
    """Adaptive range coder over symbols below n (carry-free, byte-wise)."""
    model, low, span, out = Counts(n), 0, TOP - 1, bytearray()
    for s in symbols:
        a, f = model.below(s), model.below(s + 1) - model.below(s)
        r = span // model.total
        low, span = low + r * a, r * f
        while True:
            if (low ^ (low + span)) >= BOTTOM:
                if span >= LIMIT << 4:
                    break
                span = -low & ((LIMIT << 4) - 1)
            out.append((low >> 24) & 255)
            low, span = (low << 8) & (TOP - 1), span << 8
        if model.total < LIMIT - 32:
            model.add(s, 32)
    for _ in range(4):
        out.append((low >> 24) & 255)
        low = (low << 8) & (TOP - 1)
    return bytes(out)


def range_decode(raw: bytes, count: int, n: int) -> list[int]:
    model, low, span, out = Counts(n), 0, TOP - 1, []
    at, code = 4, int.from_bytes(raw[:4], "big")
    for _ in range(count):
        r = span // model.total
        s = model.find(min(((code - low) & (TOP - 1)) // r, model.total - 1))
        a, f = model.below(s), model.below(s + 1) - model.below(s)
        low, span = low + r * a, r * f
        while True:
            if (low ^ (low + span)) >= BOTTOM:
                if span >= LIMIT << 4:
                    break
                span = -low & ((LIMIT << 4) - 1)
            code = ((code << 8) & (TOP - 1)) | (raw[at] if at < len(raw) else 0)
            at += 1
            low, span = (low << 8) & (TOP - 1), span << 8
        if model.total < LIMIT - 32:
            model.add(s, 32)
        out.append(s)
    return out


def residual_encode(u: np.ndarray, symbols: int) -> tuple[bytes, bytes]:
    """Numbers through an adaptive range coder; those beyond the alphabet are its last symbol, and eight bytes each in a stream beside it."""
    far = u >= symbols - 1
    return range_encode(np.where(far, symbols - 1, u).astype(int).tolist(), symbols), u[far].astype("<u8").tobytes()


def residual_decode(packed: bytes, beside: bytes, n: int, symbols: int) -> np.ndarray:
    u = np.array(range_decode(packed, n, symbols), np.int64)
    u[u == symbols - 1] = np.frombuffer(beside, "<u8").astype(np.int64)
    return u


def predictive_coder(track: DataFrame, o: Options, order: int = 1, symbols: int = 256) -> DataFrame:
    """Extrapolation residuals through an adaptive range coder, escapes written out; lossless says that the grid comes back from the bytes.

    Series of a block may differ in length; what pads the short ones is neither coded nor counted.
    """

    def make(ids, t0, length, y):
        q = np.floor(y + 0.5).astype(np.int64)
        real = np.arange(len(q))[:, None] < np.asarray(length)[None, :]
        r = np.diff(q, axis=0, prepend=0)
        if order == 1:
            r[2:] = np.diff(r[1:], axis=0)
        u = np.asarray(zigzag(r[real]))
        packed, beside = residual_encode(u, symbols)
        back = np.zeros_like(q)
        back[real] = unzigzag(residual_decode(packed, beside, len(u), symbols))
        if order == 1:
            back[1:] = np.cumsum(back[1:], axis=0)
        back = np.cumsum(back, axis=0)
        return [(order, u.size, len(packed) + len(beside), bool((back[real] == q[real]).all()))]

    return _blocks(track, o, "ord long, n long, packed_bytes long, lossless boolean", make)


def piece_coder(pieces: DataFrame, o: Options, symbols: int = 256) -> DataFrame:
    """Durations and displacements of each bucket's pieces, in wire order, through adaptive range coders, beside the shared-width code.

    One row a block and bucket: pieces, bytes either way, and whether the numbers came back from the coder's bytes.
    """

    def run(table: pa.Table) -> pa.Table:
        k, t0, dt, dq = (np.asarray(table.column(c)).astype(np.int64) for c in ("k", "t0", "dt", "dq"))
        order = np.lexsort((k, t0))
        size, same = 0, True
        u, d = np.asarray(zigzag(dq[order], o.zigzag)), (dt[order] - 1).astype(np.uint64)
        for x in (u, d):
            packed, beside = residual_encode(x, symbols)
            size += len(packed) + len(beside)
            same &= bool((residual_decode(packed, beside, len(x), symbols) == x.astype(np.int64)).all())
        shared = sum(len(encode(np.concatenate([u[a : a + o.chunk][::-1], d[a : a + o.chunk]]))) for a in range(0, len(u), o.chunk))
        values = (table.column("block")[0].as_py(), table.column("bucket")[0].as_py(), len(u), size, shared, same)
        return pa.table([pa.array([v], f) for v, f in zip(values, (pa.int64(), pa.int32(), pa.int64(), pa.int64(), pa.int64(), pa.bool_()), strict=True)], names=["block", "bucket", "n", "range_bytes", "shared_width_bytes", "lossless"])

    rows = pieces.withColumn("bucket", F.floor(F.col("k") / o.width).cast("int")).select("block", "bucket", "k", "t0", "dt", "dq")
    return rows.groupBy("block", "bucket").applyInArrow(run, "block long, bucket int, n long, range_bytes long, shared_width_bytes long, lossless boolean")


def fitted_codes(track: DataFrame, block: int = 4096) -> DataFrame:
    """Bits of whole numbers under codes fitted to them: Huffman, adaptive arithmetic and shared width; a block of a series at a time.

    Huffman: a block's own lengths, a table of 64 + 6 bits a symbol; arithmetic: bytes of the length classes through the range coder, the bits
    below the top one as they are; shared width: as in the chunks.
    """
    o = Options(eps=1.0, lam=1.0, step="eq", block=block, width=1)

    def make(ids, t0, length, y):
        v = np.floor(y.ravel()[: int(np.max(length))] * o.grid + 0.5).astype(np.int64)
        symbols, counts = np.unique(v, return_counts=True)
        lengths = huffman_lengths(dict(zip(symbols.tolist(), counts.tolist(), strict=True)))
        kraft = sum(2.0**-n for n in lengths.values()) <= 1
        classes = bit_lengths(v)
        packed = range_encode(classes.tolist(), 65)
        rest = int(np.maximum(classes - 1, 0).sum())
        shared = encode(v)
        return [
            ("huffman", len(v), sum(c * lengths[s] for s, c in zip(symbols.tolist(), counts.tolist(), strict=True)) + 70 * len(symbols), kraft),
            ("arithmetic", len(v), 8 * len(packed) + rest, range_decode(packed, len(v), 65) == classes.tolist()),
            ("shared_width", len(v), 8 * len(shared), bool((decode(shared, len(v)).astype(np.int64) == v).all())),
        ]

    rows = _blocks(track, o, "code string, n long, bits long, lossless boolean", make)
    return rows.groupBy("code").agg(F.sum("n").alias("n"), F.sum("bits").cast("long").alias("bits"), F.bool_and("lossless").alias("lossless"))


def huffman_lengths(counts: dict[int, int]) -> dict[int, int]:
    """Code length of each symbol."""
    import heapq

    if len(counts) < 2:
        return dict.fromkeys(counts, 1)
    heap = [(c, i, (s,)) for i, (s, c) in enumerate(sorted(counts.items()))]
    heapq.heapify(heap)
    out = dict.fromkeys(counts, 0)
    fresh = len(heap)
    while len(heap) > 1:
        a, b = heapq.heappop(heap), heapq.heappop(heap)
        for s in a[2] + b[2]:
            out[s] += 1
        heapq.heappush(heap, (a[0] + b[0], fresh, a[2] + b[2]))
        fresh += 1
    return out


HUFFMAN_SYMBOLS = 1 << 12


def huffman_bits(pieces: DataFrame) -> DataFrame:
    """Bits of durations and displacements under one Huffman code each, with an escape for all but the commonest symbols."""
    spark = pieces.sparkSession
    rows = []
    for part in ("dq", "dt"):
        top = pieces.groupBy(F.col(part).alias("s")).count().orderBy(F.desc("count"), "s").limit(HUFFMAN_SYMBOLS).collect()
        n = pieces.count()
        counts = {int(r.s): int(r["count"]) for r in top}
        rest = n - sum(counts.values())
        if rest:
            counts[1 << 62] = rest
        lengths = huffman_lengths(counts)
        bits = sum(c * lengths[s] for s, c in counts.items()) + rest * 64
        rows.append((part, n, bits, len(counts)))
    return spark.createDataFrame(rows, "part string, n long, bits long, symbols long")


def pca(track: DataFrame, ranks: list[int], limit: int = 4096) -> DataFrame:
    """Principal components of frames against the first one: share of energy kept and worst error for each rank.

    Gram matrices are summed over blocks of frames; eigenvectors of at most ``limit`` series are found on the driver and sent out.
    """
    from corridor.sources.tracks import frames

    spark = track.sparkSession
    f = frames(track)
    base = np.array(f.orderBy("t").first()["pos"])
    width = len(base)
    if width > limit:
        raise ValueError("too many series for one Gram matrix")

    def gram(batches):
        g = np.zeros((width, width))
        for b in batches:
            x = np.array(b.column("pos").to_pylist()) - base
            g += x.T @ x
        yield pa.RecordBatch.from_arrays([pa.array(np.repeat(np.arange(width), width)), pa.array(np.tile(np.arange(width), width)), pa.array(g.ravel())], ["i", "j", "v"])

    cells = f.mapInArrow(gram, "i long, j long, v double").groupBy("i", "j").agg(F.sum("v").alias("v")).collect()
    g = np.zeros((width, width))
    for r in cells:
        g[r.i, r.j] = r.v
    values, vectors = np.linalg.eigh(g)
    vectors = vectors[:, ::-1]
    energy = np.cumsum(values[::-1]) / max(values.sum(), 1e-300)

    def errors(batches):
        for b in batches:
            x = np.array(b.column("pos").to_pylist()) - base
            worst = [float(np.abs(x - (x @ vectors[:, :r]) @ vectors[:, :r].T).max()) for r in ranks]
            yield pa.RecordBatch.from_arrays([pa.array(ranks, pa.int64()), pa.array(worst)], ["r", "e"])

    worst = f.mapInArrow(errors, "r long, e double").groupBy("r").agg(F.max("e").alias("max_err"))
    kept = spark.createDataFrame([(r, float(energy[r - 1])) for r in ranks], "r long, energy double")
    return kept.join(worst, "r").select("r", F.round("energy", 6).alias("energy"), F.round("max_err", 6).alias("max_err"))


def poly_window(track: DataFrame, o: Options, degree: int = 2, window: int = 64) -> DataFrame:
    """Polynomials on windows that halve until all samples are within eps; (k, t0, n, degree) of each window kept."""
    eps = o.eps / o.grid

    def make(ids, t0, length, y):
        out = []
        for c, i in enumerate(ids):
            todo = [(a, min(a + window, int(length[c]))) for a in range(0, int(length[c]), window)][::-1]
            while todo:
                a, b = todo.pop()
                s = np.arange(b - a)
                m = min(degree, b - a - 1)
                fit = np.polynomial.Polynomial.fit(s, y[a:b, c], m, domain=[0, max(1, b - a - 1)])(s) if b > a else s
                err = float(np.abs(fit - y[a:b, c]).max()) if b > a else 0.0
                if err <= eps or b - a <= m + 1:
                    out.append((int(i), int(t0[c] + a), b - a, m, min(err, eps) * o.grid if b - a > m + 1 else err * o.grid))
                else:
                    half = (a + b) // 2
                    todo += [(half, b), (a, half)]
        return out

    return _blocks(track, o, "k long, t0 long, n long, degree long, err double", make)


def simplify(track: DataFrame, o: Options) -> DataFrame:
    """Corridor simplification by splitting at the farthest sample; (k, knots, worst vertical error) of each block."""
    eps = o.eps / o.grid

    def make(ids, t0, length, y):
        out = []
        for c, i in enumerate(ids):
            v = y[: int(length[c]), c]
            knots, worst, todo = 1, 0.0, [(0, len(v) - 1)]
            while todo:
                a, b = todo.pop()
                if b <= a:
                    continue
                line = v[a] + (v[b] - v[a]) * np.arange(b - a + 1) / (b - a)
                gap = np.abs(v[a : b + 1] - line)
                at = int(gap.argmax())
                if gap[at] <= eps:
                    knots, worst = knots + 1, max(worst, float(gap[at]))
                else:
                    todo += [(a, a + at), (a + at, b)]
            out.append((int(i), knots, worst * o.grid))
        return out

    return _blocks(track, o, "k long, knots long, err double", make)


def line_errors(v: np.ndarray) -> np.ndarray:
    """Least half width of a vertical strip around samples a..b, for all a <= b; free lines, by hulls."""
    n = len(v)
    out = np.zeros((n, n))
    for a in range(n):
        for b in range(a + 2, n):
            out[a, b] = out[a, b - 1] if out[a, b - 1] < 0 else strip(np.arange(a, b + 1), v[a : b + 1])
    return out


def _chain(t, v, sign: int) -> list[int]:
    hull: list[int] = []
    for i in range(len(t)):
        while len(hull) > 1 and sign * ((v[hull[-1]] - v[hull[-2]]) * (t[i] - t[hull[-2]]) - (v[i] - v[hull[-2]]) * (t[hull[-1]] - t[hull[-2]])) <= 0:
            hull.pop()
        hull.append(i)
    return hull


def strip(t: np.ndarray, v: np.ndarray) -> float:
    """Least half width of a vertical strip that holds all points."""
    if len(t) < 3:
        return 0.0
    best = np.inf
    upper, lower = _chain(t, v, 1), _chain(t, v, -1)
    for hull in (upper, lower):
        for a, b in zip(hull, hull[1:], strict=False):
            s = (v[b] - v[a]) / (t[b] - t[a])
            u = v[upper] - s * t[upper]
            w = v[lower] - s * t[lower]
            best = min(best, float(u.max() - w.min()) / 2)
    return best


def optimal_pieces(track: DataFrame, o: Options, family: str = "free_line") -> DataFrame:
    """Fewest disjoint pieces of a family within the line tolerance, by dynamic programming over the last piece; (k, pieces)."""
    g = o.slack + 1e-12

    def starts(v, b):
        """First samples, from the last one down, of the pieces of the family that end before b; feasibility is inherited by shorter pieces."""
        lo, hi, least, most = -np.inf, np.inf, np.inf, -np.inf
        for a in range(b - 1, -1, -1):
            if family == "free_line":  # a slope serves all samples if it serves each two of them
                if a < b - 1:
                    rise, run = v[a + 1 : b] - v[a], np.arange(1, b - a)
                    lo, hi = max(lo, ((rise - 2 * g) / run).max()), min(hi, ((rise + 2 * g) / run).min())
                if lo > hi:
                    return
            else:
                least, most = min(least, v[a]), max(most, v[a])
                if (most - least) / 2 > g:
                    return
            yield a

    def make(ids, t0, length, y):
        out = []
        for c, i in enumerate(ids):
            v = y[: int(length[c]), c]
            n = len(v)
            best = [0] + [n] * n
            for b in range(1, n + 1):
                for a in starts(v, b):
                    best[b] = min(best[b], best[a] + 1)
            out.append((int(i), best[n]))
        return out

    return _blocks(track, o, "k long, pieces long", make)


def strips(v: np.ndarray) -> np.ndarray:
    """cost[a, b]: least half width of a vertical strip that holds samples a to b - 1, infinite where b <= a.

    The best strip has the slope of two of its samples and no slope gives a narrower one, so the slopes of all pairs serve every span;
    the widths of all slopes grow sample by sample.  Holds n**3 / 2 numbers for n samples.
    """
    n = len(v)
    t = np.arange(n, dtype=np.float64)
    i, j = np.triu_indices(n, 1)
    rest = v[:, None] - t[:, None] * ((v[j] - v[i]) / (t[j] - t[i]))
    cost = np.full((n + 1, n + 1), np.inf)
    for a in range(n):
        cost[a, a + 1 : a + 3] = 0.0
        if a + 3 <= n:
            wide = np.maximum.accumulate(rest[a:], axis=0) - np.minimum.accumulate(rest[a:], axis=0)
            cost[a, a + 3 :] = wide[2:].min(axis=1) / 2
    return cost


def optimal_cover(track: DataFrame, o: Options, lines: int) -> DataFrame:
    """Least worst error of a cover by at most ``lines`` disjoint free lines (Bellman's recursion); (k, err)."""

    def make(ids, t0, length, y):
        out = []
        for c, i in enumerate(ids):
            cost = strips(y[: int(length[c]), c])
            best = cost[0].copy()
            for _ in range(lines - 1):
                best = np.maximum(best[:, None], cost).min(axis=0)
                best[0] = 0.0
            out.append((int(i), float(best[-1] * o.grid)))
        return out

    return _blocks(track, o, "k long, err double", make)
