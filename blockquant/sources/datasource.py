"""``spark.read.format('blockquant')``: packed Parquet files as plain cells, one input partition per file.

Meant for stores on a path that Python can open on every executor; for others use ``store.view``, which reads with Spark.
Rows move as Arrow batches both ways. A task writes into a staging folder and what it wrote counts only when the job commits,
so tasks that fail, run again or run twice leave nothing behind.
"""

from __future__ import annotations

import glob
import os
import uuid
from collections import Counter
from collections.abc import Iterator
from dataclasses import dataclass

import numpy as np
import pyarrow as pa
import pyarrow.compute as pc
import pyarrow.parquet as pq
from pyspark.sql.datasource import DataSource, DataSourceArrowWriter, DataSourceReader, InputPartition, WriterCommitMessage
from pyspark.sql.types import StructType

from ..operators.codec import RESTORED
from ..operators.kernels import compress_block, decompress_row
from ..schema import CodecConfig

STAGING = "_staging"


def stored_files(path: str) -> list[str]:
    every = glob.glob(os.path.join(path, "**", "*.parquet"), recursive=True)
    return sorted(f for f in every if STAGING not in f.split(os.sep))


class BlockSource(DataSource):
    @classmethod
    def name(cls) -> str:
        return "blockquant"

    def schema(self) -> str:
        return RESTORED

    def reader(self, schema: StructType) -> DataSourceReader:
        return BlockReader(self.options["path"])

    def writer(self, schema: StructType, overwrite: bool) -> DataSourceArrowWriter:
        return BlockWriter(self.options, overwrite)


class FilePart(InputPartition):
    def __init__(self, file: str) -> None:
        self.file = file


class BlockReader(DataSourceReader):
    def __init__(self, path: str) -> None:
        self.path = path.removeprefix("file://")

    def partitions(self) -> list[InputPartition]:
        return [FilePart(f) for f in stored_files(self.path)]

    def read(self, partition: FilePart) -> Iterator[pa.RecordBatch]:
        for batch in pq.ParquetFile(partition.file).iter_batches(64):
            for r in batch.to_pylist():
                c = decompress_row(r)
                n = len(c["re"])
                columns = {"block_id": np.full(n, r["block_id"], np.int64), "pol": np.full(n, r["pol"], np.int32)} | {k: c[k].astype(np.int32) for k in ("ant_a", "ant_b", "ch")} | {"row_id": c["row_id"], "re": c["re"], "im": c["im"]}
                names = ["block_id", "row_id", "ant_a", "ant_b", "ch", "pol", "re", "im"]
                yield pa.RecordBatch.from_arrays([pa.array(columns[k]) for k in names], names=names)


@dataclass
class Written(WriterCommitMessage):
    """A task's staged file, if any, and the blocks in it."""

    file: str | None
    blocks: list[int]


class BlockWriter(DataSourceArrowWriter):
    """Packs cells that come with whole blocks in a partition; a block that comes in parts is an error. Other layouts go through
    ``store.write``."""

    def __init__(self, options: dict[str, str], overwrite: bool) -> None:
        self.path, self.overwrite = options["path"].removeprefix("file://"), overwrite
        scaling = options.get("scaling", "row_channel")
        self.cfg = CodecConfig(scaling=scaling, quantiser="tgauss", trunc=2.5, bits=int(options.get("bits", "8")), autos="zero" if scaling == "antenna_channel" else "keep")

    def write(self, batches: Iterator[pa.RecordBatch]) -> Written:
        held = [b for b in batches if b.num_rows]
        if not held:
            return Written(None, [])
        cells = pa.Table.from_batches(held)
        if "flagged" not in cells.column_names:
            cells = cells.append_column("flagged", pa.array(np.zeros(cells.num_rows, bool)))
        blocks = sorted(pc.unique(cells["block_id"]).to_pylist())
        packed = [compress_block(cells.filter(pc.equal(cells["block_id"], b)), self.cfg) for b in blocks]
        os.makedirs(os.path.join(self.path, STAGING), exist_ok=True)
        file = os.path.join(self.path, STAGING, f"part-{uuid.uuid4().hex}.parquet")
        pq.write_table(pa.concat_tables(packed), file)
        return Written(file, blocks)

    def commit(self, messages: list[Written | None]) -> None:
        done = [m for m in messages if m and m.file]
        split = [b for b, n in Counter(b for m in done for b in m.blocks).items() if n > 1]
        if split:
            self.abort(messages)
            raise ValueError(f"blocks in more than one partition: {sorted(split)[:10]}; repartition by block_id first")
        old = stored_files(self.path) if self.overwrite else []
        for m in done:
            os.replace(m.file, os.path.join(self.path, os.path.basename(m.file)))
        for f in old:
            os.remove(f)
        self.clear()

    def abort(self, messages: list[Written | None]) -> None:
        for m in messages:
            if m and m.file and os.path.exists(m.file):
                os.remove(m.file)
        self.clear()

    def clear(self) -> None:
        """The staging folder goes once nothing is in it."""
        folder = os.path.join(self.path, STAGING)
        if os.path.isdir(folder) and not os.listdir(folder):
            os.rmdir(folder)
