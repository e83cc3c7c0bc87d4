"""Python data source: one row per file of a source tree, listed on the driver and read by the executors."""

from __future__ import annotations

from collections.abc import Iterator
from dataclasses import dataclass

from pyspark.sql.datasource import DataSource, DataSourceReader, InputPartition

LANGUAGES = {".py": "python", ".java": "java", ".ts": "typescript", ".js": "javascript", ".cpp": "cpp", ".cc": "cpp", ".hpp": "cpp", ".h": "cpp"}


@dataclass
class Files(InputPartition):
    paths: list[str]


class SourceTree(DataSource):
    """Options: path (any URI that pyarrow's filesystems open), suffix (only such files), files_per_task."""

    @classmethod
    def name(cls) -> str:
        return "source_tree"

    def schema(self) -> str:
        return "path string, language string, source string"

    def reader(self, schema) -> DataSourceReader:
        return TreeReader(self.options)


class TreeReader(DataSourceReader):
    def __init__(self, options):
        self.root, self.suffix, self.per_task = options["path"], options.get("suffix", ""), int(options.get("files_per_task", "256"))

    def _open(self):
        from pyarrow import fs

        return fs.FileSystem.from_uri(self.root if ":" in self.root.split("/")[0] else f"file://{self.root}")

    def partitions(self) -> list[Files]:
        from pyarrow import fs

        files, base = self._open()
        found = sorted(x.path for x in files.get_file_info(fs.FileSelector(base, recursive=True)) if x.is_file and x.path.endswith(self.suffix) and not x.base_name.startswith(("_", ".")))
        return [Files(found[i : i + self.per_task]) for i in range(0, len(found), self.per_task)] or [Files([])]

    def read(self, partition: Files) -> Iterator[tuple]:
        files, _ = self._open()
        for path in partition.paths:
            with files.open_input_stream(path, compression=None) as f:
                text = f.read().decode("utf-8", errors="replace")
            yield path, LANGUAGES.get("." + path.rsplit(".", 1)[-1]), text
