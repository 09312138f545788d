"""Histogram sort of documents into shards of near equal bytes.

The sort key is the crc32 of the text, then a hash of doc_id: equal texts stay together, and a group of equal texts that is too large
is cut by the hash.  A splitter is found by counting: the exact bytes below the boundaries of 2**ROUND_BITS equal
ranges of the part of the key space that a splitter still may lie in, summed over all partitions; each round looks that much
closer, first along the crc, then along the hash.  Probing stops where a boundary is within tolerance, so a group of equal
texts is only cut where that is needed.  Rows move once, to as many ranges as memory asks for.
"""

from __future__ import annotations

from functools import reduce

from pyspark.sql import Column, DataFrame, Window
from pyspark.sql import functions as F

from corridor.runtime import cut

ROW_BYTES = 16
ROUND_BITS = 8
CRC_BITS, TAIL_BITS = 32, 62
RANGE_ROWS = 1 << 20


def _prefix(left: int) -> list[Column]:
    """The key (crc, tail) without its last ``left`` bits, as columns."""
    if left >= TAIL_BITS:
        return [F.shiftright("crc", left - TAIL_BITS)]
    return [F.col("crc"), F.shiftright("tail", left)]


def _joined(parts, left: int) -> int:
    return int(parts[0]) if left >= TAIL_BITS else (int(parts[0]) << (TAIL_BITS - left)) | int(parts[1])


def _inside(prefixes: list[int], left: int) -> Column:
    """Whether a row's key starts with one of the prefixes."""
    if left >= TAIL_BITS:
        return F.shiftright("crc", left - TAIL_BITS).isin(prefixes)
    low = (1 << (TAIL_BITS - left)) - 1
    return reduce(lambda a, b: a | b, [(F.col("crc") == (p >> (TAIL_BITS - left))) & (F.shiftright("tail", left) == (p & low)) for p in prefixes])


def splitters(keys: DataFrame, weight: str, targets: list[float], tolerance: float) -> list[tuple[int, int]]:
    """For each target a key (crc, tail) such that the weight below it is within ``tolerance`` of the target, or as near as one key allows.

    A round is one aggregate; the driver sees at most 2**ROUND_BITS counts for each range that still holds an undecided target.
    """
    done: dict[int, int] = {}
    left = CRC_BITS + TAIL_BITS
    undecided = dict.fromkeys(range(len(targets)), (0, 0.0))  # target: its range, weight below the range
    while undecided:
        step = min(ROUND_BITS, left - TAIL_BITS if left > TAIL_BITS else left)
        prefixes = sorted({p for p, _ in undecided.values()})
        rows = keys if left == CRC_BITS + TAIL_BITS else keys.where(_inside(prefixes, left))
        left -= step
        names = [c.alias(f"b{i}") for i, c in enumerate(_prefix(left))]
        sums = rows.groupBy(*names).agg(F.sum(weight).alias("w"), F.count("*").alias("n")).collect()
        counts, single = {_joined(r, left): r["w"] for r in sums}, {_joined(r, left) for r in sums if r["n"] == 1}
        ranges: dict[int, list[int]] = {}
        for b in sorted(counts):
            ranges.setdefault(b >> step, []).append(b)
        following = {}
        for i, (p, at) in undecided.items():
            found = (p + 1) << step  # where the target is the very end
            for b in ranges.get(p, []):
                if at + counts[b] > targets[i]:
                    found = b
                    break
                at += counts[b]
            under, over = targets[i] - at, at + counts.get(found, 0) - targets[i]
            if min(under, over) > tolerance and left and found not in single:
                following[i] = (found, at)
            else:
                done[i] = (found if under <= over else found + 1) << left
        undecided = following
    return [(done[i] >> TAIL_BITS, done[i] & ((1 << TAIL_BITS) - 1)) for i in range(len(targets))]


def rank(value: Column, cuts: Column, n: int) -> Column:
    """Number of the n sorted cuts that are at or below the value, by bisection."""
    steps = F.array(*[F.lit(1 << k) for k in range(n.bit_length() - 1, -1, -1)])
    return F.aggregate(steps, F.lit(0), lambda at, k: F.when((at + k <= n) & (F.get(cuts, at + k - 1) <= value), at + k).otherwise(at))


def shards_by_bytes(docs: DataFrame, shards: int = 40, tolerance: float = 0.002) -> DataFrame:
    """doc_id, size, text_crc32, law, shard, slot, grown_shard of every row of ``docs(doc_id, text)``.

    size is the text's UTF-8 bytes (none if null) plus 16.  Shards are ranges of the key; each boundary lies within half the ``tolerance`` of
    a shard from its share of the bytes, unless a row is larger than that.  Slots count from 0 in key order without gaps.
    A null text has the key of an empty one; rows with a null doc_id or that repeat an id and a text are neighbours.
    An empty table gives an empty one.
    """
    raw = F.coalesce(F.col("text").cast("string"), F.lit("")).cast("binary")
    doc_id = F.col("doc_id").cast("long")
    keys = docs.select(doc_id.alias("doc_id"), (F.octet_length(raw) + ROW_BYTES).cast("long").alias("size"), F.crc32(raw).alias("crc"), F.shiftrightunsigned(F.xxhash64(doc_id), 64 - TAIL_BITS).alias("tail"))
    keys = cut(keys)
    total, rows = keys.agg(F.sum("size"), F.count("*")).first()
    fine = max(4, -(-rows // (shards * RANGE_ROWS)))  # ranges of a shard
    pieces = shards * fine
    bounds = sorted(splitters(keys, "size", [total * k / pieces for k in range(1, pieces)], tolerance * total / shards / 2)) if rows else [(0, 0)]
    cuts = F.array(*[F.struct(F.lit(c).cast("long"), F.lit(t).cast("long")) for c, t in bounds])
    ranged = keys.withColumn("range", rank(F.struct("crc", "tail"), cuts, len(bounds)))
    counts = {r[0]: r[1] for r in ranged.groupBy("range").count().collect()}  # a row for each range
    first, before = [], 0
    for r in range(pieces):
        before = before if r % fine else 0
        first.append(before)
        before += counts.get(r, 0)
    order = Window.partitionBy("range").orderBy("crc", "tail", F.col("doc_id").asc_nulls_first(), "size")
    slot = F.get(F.array(*[F.lit(n).cast("long") for n in first]), F.col("range")) + F.row_number().over(order) - 1
    return ranged.select("doc_id", "size", F.col("crc").alias("text_crc32"), F.lit("bytes").alias("law"), F.floor(F.col("range") / fine).cast("int").alias("shard"), slot.alias("slot"), F.lit(None).cast("int").alias("grown_shard"))
