"""Circuit text as a Python data source: ``spark.read.format("gate_text").option("path", folder).load()``."""

from __future__ import annotations

import os
import re

from pyspark.sql import SparkSession
from pyspark.sql.datasource import DataSource, DataSourceReader, InputPartition

_LINE = re.compile(r"^\s*([A-Za-z]+)\s*(?:\(([-+0-9.eE]+)\))?\s+((?:q\[\d+\]\s*,?\s*)+);")


class _File(InputPartition):
    def __init__(self, path: str):
        self.path = path


class _Reader(DataSourceReader):
    def __init__(self, folder: str):
        self.folder = folder

    def partitions(self) -> list[InputPartition]:
        return [_File(os.path.join(self.folder, f)) for f in sorted(os.listdir(self.folder)) if not f.startswith(("_", "."))]

    def read(self, partition: _File):
        net = number = 0
        with open(partition.path, encoding="utf-8") as lines:
            for line in lines:
                if line.lstrip().startswith("barrier"):
                    net += 1
                elif (m := _LINE.match(line)) and m[1].lower() not in ("qreg", "creg", "include"):
                    number += 1
                    q = [int(x) for x in re.findall(r"q\[(\d+)\]", m[3])]
                    yield os.path.basename(partition.path), number, net, m[1].upper(), q[0], q[1:], float(m[2]) if m[2] else None


class GateTextSource(DataSource):
    """One file is one circuit, named by its file name; the folder must be visible to all executors."""

    @classmethod
    def name(cls) -> str:
        return "gate_text"

    def schema(self) -> str:
        return "circuit string, gate_no bigint, net_no bigint, kind string, target int, controls array<int>, theta double"

    def reader(self, schema) -> DataSourceReader:
        return _Reader(self.options["path"])


def register(spark: SparkSession) -> None:
    spark.dataSource.register(GateTextSource)
