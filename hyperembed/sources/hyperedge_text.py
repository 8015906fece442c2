"""Data source `hyperedges`: text files with one hyperedge a line, its node ids separated by blanks.

Rows are (eid, vid); eid counts lines within a file and carries the file's number in its upper bits. The reader has one
partition a file, so memory holds one line; empty lines are hyperedges without members and give no rows.
"""

from __future__ import annotations

import os
import uuid
from dataclasses import dataclass

from pyarrow import fs as pafs
from pyspark.sql import SparkSession
from pyspark.sql.datasource import DataSource, DataSourceReader, DataSourceWriter, InputPartition, WriterCommitMessage

FILE_SHIFT = 40


class HyperedgeSource(DataSource):
    @classmethod
    def name(cls):
        return "hyperedges"

    def schema(self):
        return "eid bigint, vid bigint"

    def reader(self, schema):
        return HyperedgeReader(self.options["path"])

    def writer(self, schema, overwrite):
        return HyperedgeWriter(self.options["path"])


class HyperedgeReader(DataSourceReader):
    def __init__(self, path):
        self.path = path

    def partitions(self):
        fs, base = pafs.FileSystem.from_uri(self.path)
        info = fs.get_file_info(base)
        files = [base] if info.is_file else sorted(f.path for f in fs.get_file_info(pafs.FileSelector(base)) if f.is_file and not os.path.basename(f.path).startswith(("_", ".")))
        return [InputPartition((i, f)) for i, f in enumerate(files)]

    def read(self, partition):
        number, path = partition.value
        fs, _ = pafs.FileSystem.from_uri(self.path)
        with fs.open_input_stream(path) as f:
            rest, line = b"", 0
            while True:
                data = f.read(1 << 20)
                *lines, rest = (rest + data).split(b"\n")
                if not data and rest:
                    lines, rest = [*lines, rest], b""
                for text in lines:
                    for v in sorted(set(map(int, text.split()))):
                        yield (number << FILE_SHIFT | line, v)
                    line += 1
                if not data:
                    return


@dataclass
class Written(WriterCommitMessage):
    path: str


class HyperedgeWriter(DataSourceWriter):
    """Input rows (eid, vid) must come with all rows of a hyperedge together: partitioned and sorted by eid."""

    def __init__(self, path):
        self.path = path

    def write(self, rows):
        fs, base = pafs.FileSystem.from_uri(self.path)
        fs.create_dir(base, recursive=True)
        name = f"{base}/.{uuid.uuid4().hex}"
        with fs.open_output_stream(name) as out:
            last, members = None, []
            for eid, vid in rows:
                if eid != last and members:
                    out.write((" ".join(map(str, members)) + "\n").encode())
                    members = []
                last = eid
                members.append(vid)
            if members:
                out.write((" ".join(map(str, members)) + "\n").encode())
        return Written(name)

    def commit(self, messages):
        fs, base = pafs.FileSystem.from_uri(self.path)
        for i, m in enumerate(messages):
            if m is not None:
                fs.move(m.path, f"{base}/part-{i:05d}.txt")

    def abort(self, messages):
        fs, _ = pafs.FileSystem.from_uri(self.path)
        for m in messages:
            if m is not None:
                fs.delete_file(m.path)


def register(spark: SparkSession) -> None:
    spark.dataSource.register(HyperedgeSource)
