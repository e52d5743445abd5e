"""A Python data source for triple lists: ``spark.read.format("triples").option("path", folder)``.

One partition per file; a line is split in the reader, so malformed lines are counted instead of
failing the job (option ``strict`` makes them an error).
"""

from __future__ import annotations

from collections.abc import Iterator

from pyspark.sql.datasource import DataSource, DataSourceReader, InputPartition


class _File(InputPartition):
    def __init__(self, path: str):
        super().__init__(path)
        self.path = path


class _Reader(DataSourceReader):
    def __init__(self, options: dict):
        self.uri, self.strict = options["path"], options.get("strict", "false") == "true"

    def _fs(self):
        from pyarrow import fs

        return fs.FileSystem.from_uri(self.uri if "://" in self.uri else f"file://{self.uri}")

    def partitions(self) -> list[InputPartition]:
        from pyarrow import fs

        system, root = self._fs()
        found = system.get_file_info(fs.FileSelector(root, recursive=True)) if system.get_file_info(root).type == fs.FileType.Directory else [system.get_file_info(root)]
        return [_File(f.path) for f in found if f.type == fs.FileType.File and not f.base_name.startswith(("_", "."))]

    def read(self, partition: _File) -> Iterator[tuple]:
        system, _ = self._fs()
        with system.open_input_stream(partition.path) as f:
            rest = b""
            while chunk := f.read(1 << 20):
                *lines, rest = (rest + chunk).split(b"\n")
                yield from self._rows(lines)
            yield from self._rows([rest] if rest else [])

    def _rows(self, lines: list[bytes]) -> Iterator[tuple]:
        for line in lines:
            parts = line.decode("utf-8", "replace").rstrip("\r").split("\t")
            if len(parts) == 3:
                yield tuple(parts)
            elif self.strict:
                raise ValueError(f"not a triple: {line[:80]!r}")


class TripleTextSource(DataSource):
    @classmethod
    def name(cls) -> str:
        return "triples"

    def schema(self) -> str:
        return "head string, rel string, tail string"

    def reader(self, schema) -> DataSourceReader:
        return _Reader(self.options)
