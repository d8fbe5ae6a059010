"""A Python data source for edges: stored as Arrow files in a folder, or made as ring graphs with chords for load generation.

With a path, each task writes a file of its own and the commit lists the files of the tasks that count, so
those of failed attempts are never read; reading has a part for each listed file. Without one, edges are made.
"""

from __future__ import annotations

import json
import uuid
from dataclasses import dataclass

import pyarrow as pa
from pyarrow.fs import FileSystem, FileType
from pyspark.sql.datasource import DataSource, DataSourceArrowWriter, DataSourceReader, InputPartition, WriterCommitMessage

_LIST = "_files.json"


@dataclass
class _Wrote(WriterCommitMessage):
    name: str


class _Writer(DataSourceArrowWriter):
    def __init__(self, path: str, overwrite: bool):
        self.path, self.overwrite = path, overwrite

    def write(self, iterator):
        fs, root = FileSystem.from_uri(self.path)
        fs.create_dir(root, recursive=True)
        name, out = f"{uuid.uuid4().hex}.arrow", None
        with fs.open_output_stream(f"{root}/{name}") as file:
            for batch in iterator:
                out = out or pa.ipc.new_stream(file, batch.schema)
                out.write_batch(batch)
            if out:
                out.close()
        return _Wrote(name if out else "")

    def commit(self, messages):
        fs, root = FileSystem.from_uri(self.path)
        fs.create_dir(root, recursive=True)
        files = [] if self.overwrite else _listed(self.path)
        with fs.open_output_stream(f"{root}/{_LIST}") as file:
            file.write(json.dumps(files + [m.name for m in messages if m and m.name]).encode())


def _listed(path: str) -> list[str]:
    fs, root = FileSystem.from_uri(path)
    if fs.get_file_info(f"{root}/{_LIST}").type == FileType.NotFound:
        return []
    with fs.open_input_stream(f"{root}/{_LIST}") as file:
        return json.loads(file.read())


class _Files(DataSourceReader):
    def __init__(self, path: str):
        self.path = path

    def partitions(self):
        return [InputPartition(name) for name in _listed(self.path)] or [InputPartition("")]

    def read(self, partition):
        if partition.value:
            fs, root = FileSystem.from_uri(self.path)
            with fs.open_input_stream(f"{root}/{partition.value}") as file:
                yield from pa.ipc.open_stream(file)


class _Made(DataSourceReader):
    def __init__(self, options):
        self.n, self.parts = int(options.get("vertices", 100)), int(options.get("parts", 2))

    def partitions(self):
        return [InputPartition(i) for i in range(self.parts)]

    def read(self, partition):
        for v in range(partition.value, self.n, self.parts):
            yield (2 * v, v, (v + 1) % self.n)
            yield (2 * v + 1, v, (v * 7 + 3) % self.n)


class GraphEdges(DataSource):
    @classmethod
    def name(cls):
        return "graph_edges"

    def schema(self):
        return "seq long, src long, dst long"

    def reader(self, schema):
        return _Files(self.options["path"]) if "path" in self.options else _Made(self.options)

    def writer(self, schema, overwrite):
        return _Writer(self.options["path"], overwrite)
