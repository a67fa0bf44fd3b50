"""Python data sources: a sink of prompts as JSON lines, and a source that reads them as chunks."""

from __future__ import annotations

import json
import uuid
from dataclasses import dataclass

import pyarrow.fs as pafs
from pyspark.sql.datasource import DataSource, DataSourceReader, DataSourceWriter, InputPartition, WriterCommitMessage


def _open(path: str):
    if path.startswith("file:") and not path.startswith("file://"):
        path = "file://" + path[5:]
    return pafs.FileSystem.from_uri(path) if "://" in path else (pafs.LocalFileSystem(), path)


@dataclass
class Part(WriterCommitMessage):
    name: str
    rows: int


class PromptWriter(DataSourceWriter):
    """A file a task; only files in the manifest count, so lost tasks leave nothing visible."""

    def __init__(self, path: str):
        self.path = path

    def write(self, iterator) -> Part:
        system, base = _open(self.path)
        system.create_dir(base, recursive=True)
        name, rows = f"{uuid.uuid4().hex}.jsonl", 0
        with system.open_output_stream(f"{base}/{name}") as out:
            for r in iterator:
                out.write((json.dumps({"query_id": r.query_id, "prompt": r.prompt}) + "\n").encode())
                rows += 1
        return Part(name, rows)

    def commit(self, messages) -> None:
        system, base = _open(self.path)
        system.create_dir(base, recursive=True)
        with system.open_output_stream(f"{base}/_manifest.json") as out:
            out.write(json.dumps(sorted(m.name for m in messages if m and m.rows)).encode())

    def abort(self, messages) -> None:
        system, base = _open(self.path)
        for m in messages:
            if m:
                system.delete_file(f"{base}/{m.name}")


class PromptSink(DataSource):
    @classmethod
    def name(cls) -> str:
        return "gl_prompts"

    def writer(self, schema, overwrite):
        return PromptWriter(self.options["path"])


@dataclass
class File(InputPartition):
    name: str


class ChunkReader(DataSourceReader):
    def __init__(self, path: str, size: int):
        self.path, self.size = path, size

    def partitions(self):
        system, base = _open(self.path)
        with system.open_input_stream(f"{base}/_manifest.json") as f:
            return [File(n) for n in json.loads(f.read())] or [File("")]

    def read(self, partition):
        if not partition.name:
            return
        system, base = _open(self.path)
        with system.open_input_stream(f"{base}/{partition.name}") as f:
            for line in f.read().decode().splitlines():
                row = json.loads(line)
                words = row["prompt"].split()
                for k, i in enumerate(range(0, len(words), self.size)):
                    yield row["query_id"], k, len(words[i : i + self.size])


class ChunkSource(DataSource):
    @classmethod
    def name(cls) -> str:
        return "gl_chunks"

    def schema(self) -> str:
        return "query_id string, chunk_no int, n int"

    def reader(self, schema):
        return ChunkReader(self.options["path"], int(self.options.get("size", 256)))
