"""Stored blocks as a Spark data source: ``spark.read.format("corridor")`` decodes, with filters on t and k pushed to blocks.

A store is a folder of Parquet rows as ``compress`` makes them, and its options.  Files are opened on executors by pyarrow; the folder must
be a path that all machines share.  ``write_blocks`` and ``read_blocks`` do the same by Spark's own files, for any store Spark knows.
"""

from __future__ import annotations

import json
import uuid
from dataclasses import dataclass

import numpy as np
import pyarrow as pa
import pyarrow.dataset as ds
import pyarrow.fs as fs
import pyarrow.parquet as pq
from pyspark.sql import DataFrame
from pyspark.sql import functions as F
from pyspark.sql.datasource import DataSource, DataSourceReader, DataSourceWriter, EqualTo, GreaterThan, GreaterThanOrEqual, InputPartition, LessThan, LessThanOrEqual, WriterCommitMessage

from corridor.options import Options
from corridor.plans.codec import STORED, read_block

BLOCKS_IN_RANGE = 64


def write_blocks(stored: DataFrame, path: str, o: Options) -> None:
    """Write stored rows under ``block_range=..`` folders."""
    ranged = stored.withColumn("block_range", F.floor(F.col("block") / BLOCKS_IN_RANGE))
    ranged.repartition("block_range", "bucket").sortWithinPartitions("block", "bucket", "seq").write.mode("overwrite").partitionBy("block_range").parquet(path)


def read_blocks(spark, path: str) -> DataFrame:
    return spark.read.schema(STORED + ", block_range long").parquet(path).drop("block_range")


class CorridorSource(DataSource):
    """Options: path, and codec options as JSON in ``options``."""

    @classmethod
    def name(cls) -> str:
        return "corridor"

    def schema(self) -> str:
        return "k long, t long, x double"

    def reader(self, schema) -> CorridorReader:
        return CorridorReader(self.options)

    def writer(self, schema, overwrite: bool) -> CorridorWriter:
        return CorridorWriter(self.options["path"])


@dataclass
class Written(WriterCommitMessage):
    """A task's files, not yet under their final names."""

    files: list[str]


ROWS_HELD = 1 << 10
STORED_TYPES = [("block", pa.int64()), ("bucket", pa.int32()), ("seq", pa.int32()), ("n", pa.int32()), ("payload", pa.binary()), ("header", pa.binary())]


def file_system(path: str) -> tuple[fs.FileSystem, str]:
    """The file system of a path or URI, and the path on it."""
    return fs.FileSystem.from_uri(path) if "://" in path or path.startswith("file:") else (fs.LocalFileSystem(), path)


class CorridorWriter(DataSourceWriter):
    """Appends stored rows to a store, each under the folder of its own range of blocks; files get their names when all tasks are done.

    A task holds at most ROWS_HELD rows of a range before they go to a file.
    """

    def __init__(self, path: str) -> None:
        self.path = path

    def write(self, iterator) -> Written:
        store, root = file_system(self.path)
        held: dict[int, list] = {}
        files: list[str] = []

        def put(at: int) -> None:
            rows = held.pop(at)
            folder = f"{root}/block_range={at}"
            store.create_dir(folder, recursive=True)
            name = f"{folder}/_{uuid.uuid4().hex}.parquet"
            with store.open_output_stream(name) as out:
                pq.write_table(pa.table([pa.array([r[c] for r in rows], t) for c, t in STORED_TYPES], names=[c for c, _ in STORED_TYPES]), out)
            files.append(name)

        for r in iterator:
            at = r["block"] // BLOCKS_IN_RANGE
            held.setdefault(at, []).append(r)
            if len(held[at]) >= ROWS_HELD:
                put(at)
        for at in list(held):
            put(at)
        return Written(files)

    def _files(self, messages) -> list[str]:
        return [f for m in messages if m is not None for f in m.files]

    def commit(self, messages) -> None:
        store, _ = file_system(self.path)
        for name in self._files(messages):
            folder, _, last = name.rpartition("/")
            store.move(name, f"{folder}/{last[1:]}")

    def abort(self, messages) -> None:
        store, _ = file_system(self.path)
        for name in self._files(messages):
            store.delete_file(name)


class CorridorReader(DataSourceReader):
    def __init__(self, options: dict) -> None:
        self.path, self.o = options["path"], Options(**json.loads(options.get("options", "{}")))
        self.low, self.high, self.ks = -(1 << 62), 1 << 62, None

    def pushFilters(self, filters):  # noqa: N802
        """Bounds on t and an equality on k choose blocks and buckets; Spark still tests every row."""
        for f in filters:
            column = f.attribute[0] if getattr(f, "attribute", None) else None
            if column == "t" and isinstance(f, (EqualTo, GreaterThan, GreaterThanOrEqual)):
                self.low = max(self.low, f.value)
            if column == "t" and isinstance(f, (EqualTo, LessThan, LessThanOrEqual)):
                self.high = min(self.high, f.value)
            if column == "k" and isinstance(f, EqualTo):
                self.ks = f.value
            yield f

    def _wanted(self):
        want = (ds.field("block") >= self.low // self.o.block) & (ds.field("block") <= self.high // self.o.block)
        return want if self.ks is None else want & (ds.field("bucket") == self.ks // self.o.width)

    def partitions(self):
        found = ds.dataset(self.path, partitioning="hive").to_table(columns=["block", "bucket"], filter=self._wanted() & (ds.field("seq") == -1))
        return [InputPartition(x) for x in sorted(zip(found.column("block").to_pylist(), found.column("bucket").to_pylist(), strict=True))] or [InputPartition(None)]

    def read(self, partition):
        if partition.value is None:
            return
        block, bucket = partition.value
        rows = ds.dataset(self.path, partitioning="hive").to_table(filter=(ds.field("block") == block) & (ds.field("bucket") == bucket))
        (i, t, d, p, v), (ids, t0, _, q) = read_block(rows.select(["block", "bucket", "seq", "n", "payload", "header"]), self.o)
        s = np.arange(int(d.sum())) - np.repeat(np.cumsum(d) - d, d) + 1
        piece = np.repeat(np.arange(len(d)), d)
        k, steps = np.concatenate([ids, ids[i[piece]]]), np.concatenate([t0, t[piece] + s])
        x = np.concatenate([q * self.o.grid, self.o.grid * (p[piece] + v[piece] * s / d[piece])])
        yield pa.RecordBatch.from_arrays([pa.array(k, pa.int64()), pa.array(steps, pa.int64()), pa.array(x)], ["k", "t", "x"])
