"""A Python data source ``folded`` over local or mounted directories of JSON lines with triples, for readers without Parquet."""

from __future__ import annotations

import json
import os
import uuid
from collections.abc import Iterator

from pyspark.sql.datasource import DataSource, DataSourceReader, DataSourceWriter, InputPartition, WriterCommitMessage
from pyspark.sql.types import StructType

SCHEMA = "unit_id bigint, n bigint, residual array<int>, factors array<struct<a:bigint,len:int>>, kinds array<int>, steps int"


class FoldedSource(DataSource):
    @classmethod
    def name(cls) -> str:
        return "folded"

    def schema(self) -> str:
        return SCHEMA

    def reader(self, schema: StructType) -> DataSourceReader:
        return FoldedReader(self.options["path"])

    def writer(self, schema: StructType, overwrite: bool) -> DataSourceWriter:
        return FoldedWriter(self.options["path"], overwrite)


class FoldedReader(DataSourceReader):
    def __init__(self, path: str) -> None:
        self.path = path

    def partitions(self) -> list[InputPartition]:
        return [InputPartition(f) for f in sorted(os.listdir(self.path)) if f.endswith(".jsonl")]

    def read(self, partition: InputPartition) -> Iterator[tuple]:
        with open(f"{self.path}/{partition.value}", encoding="utf-8") as f:
            for line in f:
                u, n, r, fac, k, s = json.loads(line)
                yield u, n, r, None if fac is None else [{"a": a, "len": x} for a, x in fac], k, s


class FoldedWriter(DataSourceWriter):
    """Each task writes one file under a name of its own; it counts when the task commits, and a failed job's files go."""

    def __init__(self, path: str, overwrite: bool) -> None:
        self.path = path
        os.makedirs(path, exist_ok=True)
        for f in os.listdir(path) if overwrite else ():
            os.remove(f"{path}/{f}")

    def write(self, rows) -> WriterCommitMessage:
        name = f"{self.path}/.{uuid.uuid4().hex}"
        with open(name, "w", encoding="utf-8") as f:
            for r in rows:
                fac = None if r.factors is None else [[x["a"], x["len"]] for x in r.factors]
                f.write(json.dumps([r.unit_id, r.n, r.residual, fac, r.kinds, r.steps]) + "\n")
        message = WriterCommitMessage()
        message.name = name
        return message

    def commit(self, messages) -> None:
        for m in messages:
            if m is not None:
                os.rename(m.name, f"{self.path}/part-{os.path.basename(m.name)[1:]}.jsonl")

    def abort(self, messages) -> None:
        for m in messages:
            if m is not None and os.path.exists(m.name):
                os.remove(m.name)
