"""A Python data source for token shards: folders of fixed-width binary files, one sample after another."""

from __future__ import annotations

import os
import uuid
from collections.abc import Iterator
from dataclasses import dataclass

import numpy as np
from pyspark.sql import SparkSession
from pyspark.sql.datasource import DataSource, DataSourceReader, DataSourceWriter, InputPartition, WriterCommitMessage
from pyspark.sql.types import StructType


@dataclass
class Shard(InputPartition):
    path: str


@dataclass
class Written(WriterCommitMessage):
    path: str
    samples: int


class ShardReader(DataSourceReader):
    def __init__(self, folder: str, length: int) -> None:
        self.folder, self.length = folder, length

    def partitions(self) -> list[Shard]:
        return [Shard(os.path.join(self.folder, f)) for f in sorted(os.listdir(self.folder)) if f.endswith(".tokens")]

    def read(self, partition: Shard) -> Iterator[tuple]:
        data = np.fromfile(partition.path, np.int32)
        for n, row in enumerate(data.reshape(-1, self.length)):
            yield os.path.basename(partition.path), n, row.tolist()


class ShardWriter(DataSourceWriter):
    """Each task writes a file of its own under a temporary name; the commit gives the files their final names."""

    def __init__(self, folder: str, length: int) -> None:
        self.folder, self.length = folder, length

    def write(self, rows: Iterator) -> Written:
        os.makedirs(self.folder, exist_ok=True)
        path, n = os.path.join(self.folder, f"{uuid.uuid4().hex}.open"), 0
        with open(path, "wb") as f:
            for row in rows:
                ids = np.asarray(row[-1], np.int32)
                if len(ids) != self.length:
                    raise ValueError(f"a sample has {len(ids)} tokens, the shard {self.length}")
                f.write(ids.tobytes())
                n += 1
        return Written(path, n)

    def commit(self, messages: list[Written | None]) -> None:
        for n, m in enumerate(m for m in messages if m is not None):
            if m.samples:
                os.replace(m.path, os.path.join(self.folder, f"part-{n:05d}.tokens"))
            else:
                os.remove(m.path)

    def abort(self, messages: list[Written | None]) -> None:
        for m in messages:
            if m is not None and os.path.exists(m.path):
                os.remove(m.path)


class TokenShards(DataSource):
    """``spark.read.format("token_shards").option("length", n).load(folder)``; the folder must be on a file system
    that all executors share. Rows are (shard, place, ids); the writer takes the last column as ids."""

    @classmethod
    def name(cls) -> str:
        return "token_shards"

    def schema(self) -> str:
        return "shard string, place int, ids array<int>"

    def _where(self) -> tuple[str, int]:
        return self.options["path"].removeprefix("file:"), int(self.options["length"])

    def reader(self, schema: StructType) -> ShardReader:
        return ShardReader(*self._where())

    def writer(self, schema: StructType, overwrite: bool) -> ShardWriter:
        return ShardWriter(*self._where())


def register(spark: SparkSession) -> None:
    from spanfocus.session import ship_package

    ship_package(spark)
    spark.dataSource.register(TokenShards)
