"""Exact Jaccard self-join of documents on distinct word shingles, by vertical partitioning.

Shingles are ordered by a 64-bit hash, a global order that every document shares, and the order is cut into fragments.

Filter.  Linked documents share at least the threshold's part of either set.  Every fragment counts, for each document, the
shingles in it that some other set has too; the partial counts are summed per document, and whoever falls short has no
links.  A slice of input settles what it can see itself and sends each shingle on once, in few bytes; shortened hashes
can only count too much.  Equal sets are one class from the start.

Candidates.  Among the documents left, shingles are ordered by frequency, then hash, and linked documents agree on one of the
first n - ceil(t n) + 1 of either.  Documents that meet there, directly or over others, form a cluster.

Counting.  Inside a cluster, cut into tiles where it is large, the overlaps of all pairs of two tiles are counted vertically: each
document's shingles are cut at the same places of the global order into ``FRAGMENTS`` pieces, a task has one fragment of one pair of
tiles, and counts the partial overlaps as products of 0/1 matrices over the shingles that two members share.  A pair that misses more in
one fragment than a link may miss in all is dropped there.  The partial counts of the others travel as one packed row for a fragment of a
pair of tiles, are summed per pair, and tested in integers.  A pair of tiles returns a spanning forest of its links, so
no row is ever a pair of documents.
"""

from __future__ import annotations

from dataclasses import dataclass

import numpy as np
import pyarrow as pa
from pyspark.sql import Column, DataFrame, Window
from pyspark.sql import functions as F

from corridor.llm import texthash as T
from corridor.llm.components import components, spanning_stars
from corridor.runtime import cut

TILE_DOCS, TILE_GRAMS = 256, 1 << 20
FRAGMENT_BITS = 2
FRAGMENTS = 1 << FRAGMENT_BITS
MOST_PARTS = 1 << 14  # of the filter's exchange: a slice of input sends a pack to each at most
BROADCAST_ROWS = 1 << 20
U32 = np.uint64(32)


@dataclass(frozen=True)
class Similarity:
    """Documents link when den * intersection >= num * union over shingles of ``k`` words."""

    k: int = 5
    num: int = 80
    den: int = 100
    lower: bool = True

    def reach(self, n: Column) -> Column:
        """Smallest overlap that a set of n shingles has with any linked one."""
        return F.ceil(n * self.num / self.den)


def _identity(h: np.ndarray, doc: np.ndarray, rows: int) -> tuple[np.ndarray, np.ndarray, np.ndarray]:
    """Size and two independent 64-bit sums of each document's set."""
    n = np.bincount(doc, minlength=rows)
    first = np.zeros(rows, np.uint64)
    second = np.zeros(rows, np.uint64)
    full = np.flatnonzero(n)
    if len(full):
        at = np.searchsorted(doc, full)
        first[full] = np.add.reduceat(T.mix(h ^ np.uint64(0x1234567)), at)
        second[full] = np.add.reduceat(T.mix(h + np.uint64(0x9E3779B9)), at)
    return n, first, second


def _sets(batch: pa.RecordBatch, sim: Similarity):
    """Slices of a batch (doc_id, text) as (doc ids, hashes, document index, sizes, two sums)."""
    texts = batch.column(1)
    for a, b in T.slices(texts):
        h, doc = T.gram_sets(T.words(texts[a:b], sim.lower), sim.k)
        yield batch.column(0)[a:b].fill_null(0).to_numpy(zero_copy_only=False), h, doc, *_identity(h, doc, b - a)


def profile(docs: DataFrame, sim: Similarity) -> DataFrame:
    """(doc_id, n_shingles, s1, s2): equal sizes and sums mean equal sets."""

    def run(batches):
        for batch in batches:
            at = 0
            for _, _, _, n, s1, s2 in _sets(batch, sim):
                ids = batch.column(0)[at : at + len(n)]
                at += len(n)
                yield pa.RecordBatch.from_arrays([ids, pa.array(n.astype(np.int64)), pa.array(s1.view(np.int64)), pa.array(s2.view(np.int64))], ["doc_id", "n_shingles", "s1", "s2"])

    return docs.select(F.col("doc_id").cast("long"), F.col("text").cast("string")).mapInArrow(T.tidy(run), "doc_id long, n_shingles long, s1 long, s2 long")


def _groups(keys: np.ndarray) -> tuple[np.ndarray, np.ndarray]:
    """First positions of the runs of a sorted array, and the number of the run that each item is in."""
    new = np.ones(len(keys), bool)
    new[1:] = keys[1:] != keys[:-1]
    return np.flatnonzero(new), np.cumsum(new) - 1


def shared_counts(docs: DataFrame, sim: Similarity, total: int) -> DataFrame:
    """(s1, shared): for each set, how many of its shingles some other set has; at times a few too many, never too few."""
    tasks = min(MOST_PARTS, max(8, total >> 21))
    parts, key_of = tasks, T.even_keys(tasks).astype(np.int32)
    sums = max(8, tasks // 4)
    sum_key = T.even_keys(sums).astype(np.int32)

    def send(batches):
        for batch in batches:
            for _, h, doc, _, s1, _ in _sets(batch, sim):
                if not len(h):
                    continue
                own = s1[doc]
                order = np.lexsort((own, h))
                h, own = h[order], own[order]
                once = np.ones(len(h), bool)
                once[1:] = (h[1:] != h[:-1]) | (own[1:] != own[:-1])
                h, own = h[once], own[once]
                at, run = _groups(h)
                many = np.diff(np.append(at, len(h))) > 1
                known, n_known = np.unique(own[many[run]], return_counts=True)
                seen = h[at[many]]
                lone = ~many[run]
                h, own = h[lone], own[lone]
                part, seen_part = (h % np.uint64(parts)).astype(np.int64), (seen % np.uint64(parts)).astype(np.int64)
                order = np.lexsort((own, part))
                h, own, part = h[order], own[order], part[order]
                order = np.argsort(seen_part, kind="stable")
                seen, seen_part = seen[order], seen_part[order]
                short, seen = (h >> U32).astype(np.uint32), (seen >> U32).astype(np.uint32)
                there = np.union1d(np.union1d(part, seen_part), [0])  # only parts that get something, and one for what is known here
                rows = []
                for p, x, y, u, v in zip(there.tolist(), *(np.searchsorted(c, there, side) for c in (part, seen_part) for side in ("left", "right")), strict=True):
                    first, run = _groups(own[x:y])
                    n = np.diff(np.append(first, y - x)).astype(np.uint32)
                    local = (known.tobytes(), n_known.astype(np.uint32).tobytes()) if p == 0 else (b"", b"")
                    rows.append((p, short[x:y].tobytes(), own[x:y][first].tobytes(), n.tobytes(), seen[u:v].tobytes(), *local))
                columns = list(zip(*rows, strict=True))
                yield pa.RecordBatch.from_arrays([pa.array(key_of[list(columns[0])]), *(pa.array(c, pa.binary()) for c in columns[1:])], ["part", "grams", "sets", "sizes", "seen", "known", "n_known"])

    def meet(batches):
        def array(column, kind):
            return [np.frombuffer(x.as_buffer(), kind) for x in column]

        keys, sets, marks = [], [], []
        for batch in batches:
            part = batch.column("part").to_pylist()
            grams, seen = array(batch.column("grams"), np.uint32), array(batch.column("seen"), np.uint32)
            for p, g, s, c, n in zip(part, grams, seen, array(batch.column("sets"), np.uint64), array(batch.column("sizes"), np.uint32), strict=True):
                keys.append(g.astype(np.uint64) | np.uint64(p) << U32)
                sets.append(np.repeat(c, n))
                marks.append(s.astype(np.uint64) | np.uint64(p) << U32)
            for c, n in zip(array(batch.column("known"), np.uint64), array(batch.column("n_known"), np.uint32), strict=True):
                if len(c):  # settled where they were read
                    yield dealt(c, n)
        if not keys:
            return
        key, own, mark = np.concatenate(keys), np.concatenate(sets), np.unique(np.concatenate(marks))
        keys.clear()
        sets.clear()
        order = np.argsort(key)
        key, own = key[order], own[order]
        del order
        at, run = _groups(key)
        if not len(at):
            return
        shared = np.minimum.reduceat(own, at) != np.maximum.reduceat(own, at)
        if len(mark):
            shared |= mark[np.minimum(np.searchsorted(mark, key[at]), len(mark) - 1)] == key[at]
        if shared.any():
            yield dealt(*np.unique(own[shared[run]], return_counts=True))

    def dealt(sets: np.ndarray, n: np.ndarray) -> pa.RecordBatch:
        """Partial counts, packed by where their sets are summed."""
        to = (sets % np.uint64(sums)).astype(np.int64)
        order = np.argsort(to, kind="stable")
        sets, n = sets[order], n[order].astype(np.uint32)
        full, at = np.unique(to[order], return_index=True)
        ends = np.append(at[1:], len(sets))
        packed = [[x[a:b].tobytes() for a, b in zip(at, ends, strict=True)] for x in (sets, n)]
        return pa.RecordBatch.from_arrays([pa.array(sum_key[full]), pa.array(packed[0], pa.binary()), pa.array(packed[1], pa.binary())], ["to", "sets", "n"])

    def add(batches):
        sets, n = [], []
        for batch in batches:
            sets += [np.frombuffer(x.as_buffer(), np.uint64) for x in batch.column("sets")]
            n += [np.frombuffer(x.as_buffer(), np.uint32) for x in batch.column("n")]
            if sum(map(len, sets)) > 1 << 21:  # keeps the state near the number of sets
                sets, n = ([x] for x in total_of(sets, n))
        if sets:
            one, count = total_of(sets, n)
            for i in range(0, len(one), 1 << 16):
                yield pa.RecordBatch.from_arrays([pa.array(one[i : i + (1 << 16)].view(np.int64)), pa.array(count[i : i + (1 << 16)].astype(np.int64))], ["s1", "shared"])

    def total_of(sets, n):
        one, at = np.unique(np.concatenate(sets), return_inverse=True)
        return one, np.bincount(at, np.concatenate(n)).astype(np.int64)

    schema = "part int, grams binary, sets binary, sizes binary, seen binary, known binary, n_known binary"
    packs = docs.select(F.col("doc_id").cast("long"), F.col("text").cast("string")).where("doc_id is not null").mapInArrow(T.tidy(send), schema)
    partial = packs.repartition(tasks, "part").mapInArrow(T.tidy(meet), "to int, sets binary, n binary")
    return partial.repartition(sums, "to").mapInArrow(T.tidy(add), "s1 long, shared long")


def _with_grams(docs: DataFrame, wanted: DataFrame, sim: Similarity) -> DataFrame:
    """(doc_id, n_shingles, grams) of the documents in ``wanted(doc_id, n_shingles)``."""

    def run(batches):
        for batch in batches:
            for ids, h, doc, n, _, _ in _sets(batch, sim):
                offsets = np.concatenate([[0], np.cumsum(n)]).astype(np.int32)
                yield pa.RecordBatch.from_arrays([pa.array(ids), pa.array(n.astype(np.int64)), pa.ListArray.from_arrays(pa.array(offsets), pa.array(h.view(np.int64)))], ["doc_id", "n_shingles", "grams"])

    ids = wanted.select("doc_id").distinct()
    ids = F.broadcast(ids) if ids.count() <= BROADCAST_ROWS else ids
    texts = docs.select(F.col("doc_id").cast("long"), F.col("text").cast("string")).join(ids, "doc_id")
    return texts.mapInArrow(T.tidy(run), "doc_id long, n_shingles long, grams array<bigint>")


def _candidates(left: DataFrame, sim: Similarity) -> DataFrame:
    """Links of documents that agree on a shingle of their prefixes, each to the smallest document there."""
    rows = left.select("doc_id", "n_shingles", F.explode("grams").alias("gram"))
    often = rows.groupBy("gram").agg(F.count("*").alias("df")).where("df > 1")
    rows = rows.join(often, "gram")
    by = Window.partitionBy("doc_id", "n_shingles")
    place = rows.select("doc_id", "gram", "n_shingles", F.row_number().over(by.orderBy("df", "gram")).alias("at"), F.count("*").over(by).alias("common"))
    # shingles of one document alone come first in the order and match nothing
    prefix = cut(place.where(F.col("at") + F.col("n_shingles") - F.col("common") <= F.col("n_shingles") - sim.reach(F.col("n_shingles")) + 1).select("doc_id", "gram"))
    least = prefix.groupBy("gram").agg(F.min("doc_id").alias("least"))
    return prefix.join(least, "gram").where("doc_id <> least").select(F.col("doc_id").alias("a"), F.col("least").alias("b")).distinct()


def overlaps(h: np.ndarray, row: np.ndarray, left: int, right: int, columns: int = 4096) -> np.ndarray:
    """Intersection sizes of the first ``left`` sets with the ``right`` ones after them, or with each other if there are none."""
    out = np.zeros((left, right or left), np.float32)
    order = np.argsort(h, kind="stable")
    h, row = h[order], row[order]
    new = np.ones(len(h), bool)
    new[1:] = h[1:] != h[:-1]
    gram = np.cumsum(new) - 1
    shared = np.bincount(gram)[gram] > 1 if len(gram) else new
    gram, row = gram[shared], row[shared]
    if not len(gram):
        return out
    gram = np.unique(gram, return_inverse=True)[1]
    step = min(columns, int(gram[-1]) + 1)
    for a in range(0, int(gram[-1]) + 1, step):
        lo, hi = np.searchsorted(gram, (a, a + step))
        m = np.zeros((left + right, step), np.float32)
        m[row[lo:hi], gram[lo:hi] - a] = 1
        out += m[:left] @ (m[left:] if right else m).T
    return out


def need(sim: Similarity, a: np.ndarray, b: np.ndarray) -> np.ndarray:
    """Smallest overlap that links sets of these sizes, for all pairs."""
    return -(-sim.num * (a[:, None] + b[None, :]) // (sim.den + sim.num))


def partial_counts(sim: Similarity, pieces: list[np.ndarray], sizes: np.ndarray, left: int) -> tuple[np.ndarray, np.ndarray]:
    """Of all pairs of the first ``left`` documents with those after them (with each other if there are none): whether the pair can still be linked
    as far as this fragment tells, and the partial overlaps of those that can, in order.

    pieces: the shingles that each document has in the fragment; sizes: of its whole set.
    """
    right = len(pieces) - left
    own = np.array([len(p) for p in pieces])
    count = overlaps(np.concatenate(pieces), np.repeat(np.arange(len(pieces)), own), left, right).astype(np.int64)
    cols = slice(left, None) if right else slice(None)
    least = need(sim, sizes[:left], sizes[cols])
    able = (own[:left, None] - count <= sizes[:left, None] - least) & (own[None, cols] - count <= sizes[None, cols] - least)
    if not right:
        able = np.triu(able, 1)
    return able, count[able]


def pack_counts(able: np.ndarray, count: np.ndarray) -> tuple[bytes, bytes]:
    kind = np.uint8 if not len(count) or count.max() < 256 else np.uint32
    return np.packbits(able).tobytes(), bytes([kind().itemsize]) + count.astype(kind).tobytes()


def sum_counts(packed: list[tuple[bytes, bytes]], pairs: int) -> tuple[np.ndarray, np.ndarray]:
    """Pairs that no fragment has dropped, and the sums of their partial counts."""
    masks = [np.unpackbits(np.frombuffer(m, np.uint8), count=pairs).astype(bool) for m, _ in packed]
    able = np.logical_and.reduce(masks)
    total = np.zeros(int(able.sum()), np.int64)
    for mask, (_, raw) in zip(masks, packed, strict=True):
        total += np.frombuffer(raw, np.uint8 if raw[0] == 1 else np.uint32, offset=1)[able[mask]]
    return np.flatnonzero(able), total


def links(docs: DataFrame, classes: DataFrame, sim: Similarity, total: int) -> DataFrame:
    """Links (a, b) that span all groups of similar sets among the ``classes(rep, n_shingles, s1, s2)``.

    total: number of shingles of all documents, from which the number of tasks follows.
    """
    spread = int(docs.sparkSession.conf.get("spark.sql.shuffle.partitions"))
    counts = shared_counts(docs, sim, total)
    left = classes.join(counts, "s1").where(F.col("shared") >= sim.reach(F.col("n_shingles")))
    left = cut(left.select(F.col("rep").alias("doc_id"), "n_shingles", "s1", "s2"))
    grams = cut(_with_grams(docs, left, sim))
    near = components(_candidates(grams, sim)).withColumnRenamed("vertex", "doc_id")
    near = cut(near.join(left.groupBy("doc_id").agg(F.max("n_shingles").alias("n_shingles")), "doc_id"))
    sizes = near.groupBy("component").agg(F.count("*").alias("members"), F.sum("n_shingles").alias("grams"))
    sizes = sizes.select("component", F.greatest(F.ceil(F.col("members") / TILE_DOCS), F.ceil(F.col("grams") / TILE_GRAMS)).cast("int").alias("tiles"))
    near = near.join(sizes, "component").withColumn("tile", F.pmod(F.xxhash64("doc_id"), F.col("tiles")).cast("int"))
    units = max(64, spread, near.count() // 1000)
    # small clusters share units by hash; of a large one, every pair of tiles is a unit
    pairs = F.expr("transform(sequence(0, tiles - 1), j -> struct(least(tile, j) as i, greatest(tile, j) as j))")
    near = near.withColumn("pair", F.explode(pairs)).select(
        "doc_id", "component", "tile", "n_shingles", F.col("pair.i").alias("i"), F.col("pair.j").alias("j"),
        F.when(F.col("tiles") == 1, F.pmod(F.xxhash64("component"), F.lit(units))).otherwise(F.xxhash64("component", "pair")).alias("unit"),
    )
    # the global order is that of the hashes; its first bits name the fragment
    cut_up = F.expr(f"transform(sequence(0, {FRAGMENTS - 1}), f -> filter(grams, g -> shiftrightunsigned(g, {64 - FRAGMENT_BITS}) = f))")
    pieces = grams.select("doc_id", F.posexplode(cut_up).alias("fragment", "piece"))

    def count(table: pa.Table) -> pa.Table:
        groups: dict[tuple, list] = {}
        names = ("component", "i", "j", "tile", "doc_id", "n_shingles")
        for (c, i, j, *row), g in zip(zip(*(table.column(x).to_pylist() for x in names), strict=True), (x for chunk in table.column("piece").chunks for x in chunk), strict=True):
            groups.setdefault((c, i, j), []).append((*row, np.asarray(g.values).view(np.uint64)))
        rows = []
        for (c, i, j), docs in groups.items():
            docs.sort(key=lambda d: (d[0] != i, d[1]))  # one order in all fragments
            left = sum(d[0] == i for d in docs)
            if not left or i != j and left == len(docs):
                continue
            ids, sizes = np.array([d[1] for d in docs]), np.array([d[2] for d in docs])
            rows.append((c, i, j, left, ids.tobytes(), sizes.tobytes(), *pack_counts(*partial_counts(sim, [d[3] for d in docs], sizes, left))))
        columns = list(zip(*rows, strict=True)) or [()] * 8
        kinds = [pa.int64(), pa.int32(), pa.int32(), pa.int32(), *[pa.binary()] * 4]
        return pa.Table.from_arrays([pa.array(x, k) for x, k in zip(columns, kinds, strict=True)], ["component", "i", "j", "left", "ids", "sizes", "able", "counts"])

    def judge(table: pa.Table) -> pa.Table:
        groups: dict[tuple, list] = {}
        for r in table.to_pylist():
            groups.setdefault((r["component"], r["i"], r["j"]), []).append(r)
        us, vs = [np.zeros(0, np.int64)], [np.zeros(0, np.int64)]
        for rows in groups.values():
            ids, sizes = (np.frombuffer(rows[0][x], np.int64) for x in ("ids", "sizes"))
            left = rows[0]["left"]
            skip = left if left < len(ids) else 0  # where the second tile begins
            across = len(ids) - skip
            at, total = sum_counts([(r["able"], r["counts"]) for r in rows], left * across)
            x, y = at // across, at % across + skip
            linked = sim.den * total >= sim.num * (sizes[x] + sizes[y] - total)
            u, v = spanning_stars(ids[x[linked]], ids[y[linked]])
            us.append(u)
            vs.append(v)
        return pa.table({"a": pa.array(np.concatenate(us)), "b": pa.array(np.concatenate(vs))})

    partial = near.join(pieces, "doc_id").groupBy("unit", "fragment").applyInArrow(T.tidy(count), "component long, i int, j int, left int, ids binary, sizes binary, able binary, counts binary")
    meet = F.pmod(F.xxhash64("component", "i", "j"), F.lit(units * FRAGMENTS))  # small clusters share a call
    return partial.withColumn("meet", meet).groupBy("meet").applyInArrow(T.tidy(judge), "a long, b long")


def jaccard_components(docs: DataFrame, sim: Similarity = Similarity()) -> DataFrame:
    """(doc_id, n_shingles, component_id) of every row of ``docs(doc_id, text)``.

    component_id is the smallest doc_id reachable over links.  Null or empty texts, and those without words, have no
    shingles and are linked with nothing.  Rows that repeat a doc_id stay, each with the values of its own text; links
    of either count for the id.  A null doc_id gets a null component.  An empty table gives an empty one.
    """
    docs = T.bounded(docs)
    own = cut(profile(docs, sim))
    classes = own.where("n_shingles > 0 and doc_id is not null").groupBy("n_shingles", "s1", "s2").agg(F.min("doc_id").alias("rep"))
    classes = cut(classes)
    total = own.agg(F.sum("n_shingles")).first()[0] or 0
    groups = components(links(docs, classes, sim, total))
    named = classes.join(groups, classes.rep == groups.vertex, "left").select("n_shingles", "s1", "s2", F.coalesce("component", "rep").alias("named"))
    out = own.join(named, ["n_shingles", "s1", "s2"], "left")
    return out.select("doc_id", "n_shingles", F.when(F.col("doc_id").isNotNull(), F.coalesce("named", "doc_id")).alias("component_id"))
