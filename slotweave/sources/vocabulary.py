"""A Python data source for the vocabulary text of a bundle: a token per line in hex, in the order of the exported ids."""

from __future__ import annotations

import os
from collections.abc import Iterator

from pyarrow import fs
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql.datasource import DataSource, DataSourceReader, InputPartition

NAME = "vocabulary_text"


class TextFile(InputPartition):
    def __init__(self, path: str):
        super().__init__(path)
        self.path = path


def _opened(path: str) -> tuple[fs.FileSystem, str]:
    """The file system of a URI that Arrow knows, or the local one for a plain path."""
    return fs.FileSystem.from_uri(path) if "://" in path or path.startswith("file:") else (fs.LocalFileSystem(), os.path.abspath(path))


class VocabularyReader(DataSourceReader):
    def __init__(self, path: str):
        self.path = path

    def partitions(self) -> list[InputPartition]:
        """One for each file; those that Spark marks as hidden are none of the vocabulary."""
        store, path = _opened(self.path)
        found = store.get_file_info(path)
        if found.type == fs.FileType.NotFound:
            raise FileNotFoundError(self.path)
        files = [found] if found.type == fs.FileType.File else store.get_file_info(fs.FileSelector(path))
        seen = sorted(f.base_name for f in files if f.type == fs.FileType.File and not f.base_name.startswith(("_", ".")))
        return [TextFile(self.path if found.type == fs.FileType.File else f"{self.path.rstrip('/')}/{name}") for name in seen]

    def read(self, partition: TextFile) -> Iterator[tuple]:
        store, path = _opened(partition.path)
        rest, line = b"", 0
        with store.open_input_stream(path) as file:
            while block := file.read(1 << 20):
                *whole, rest = (rest + block).split(b"\n")
                for text in whole:
                    yield os.path.basename(path), line, bytes.fromhex(text.decode("ascii"))
                    line += 1
        if rest:
            yield os.path.basename(path), line, bytes.fromhex(rest.decode("ascii"))


class VocabularySource(DataSource):
    """Option path: a file or a folder of files. A line that isn't hex fails the read; an empty folder has no rows."""

    @classmethod
    def name(cls) -> str:
        return NAME

    def schema(self) -> str:
        return "file string, line long, token binary"

    def reader(self, schema) -> DataSourceReader:
        if not self.options.get("path"):
            raise ValueError("no path is given")
        return VocabularyReader(self.options["path"])


def read_vocabulary(spark: SparkSession, path: str) -> DataFrame:
    """file, line from 0, token: line n of a bundle's single file is the n-th of its exported ids."""
    spark.dataSource.register(VocabularySource)
    return spark.read.format(NAME).load(path)
