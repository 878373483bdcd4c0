"""A Python Data Source that replays recorded answers: `spark.read.format("recorded_answers").option("path", ...)`.

The path is a folder of JSON lines (target, anchor, hop, iter, text) that all executors reach; each file is a partition, so
a large recording is read in parallel and nothing passes through the driver. A table function gives words with their places.
"""

from __future__ import annotations

import json
from collections.abc import Iterator

from pyspark.sql import SparkSession
from pyspark.sql.datasource import DataSource, DataSourceReader, InputPartition

SCHEMA = "target string, anchor string, hop int, iter int, text string"


class _File(InputPartition):
    def __init__(self, path: str):
        self.path = path


class _Reader(DataSourceReader):
    def __init__(self, folder: str):
        self.folder = folder

    def _fs(self):
        from pyarrow import fs

        return fs.FileSystem.from_uri(self.folder if "://" in self.folder else f"file://{self.folder}")

    def partitions(self) -> list[InputPartition]:
        from pyarrow import fs

        system, path = self._fs()
        return [_File(f.path) for f in system.get_file_info(fs.FileSelector(path)) if f.is_file and not f.base_name.startswith(("_", "."))]

    def read(self, partition: _File) -> Iterator[tuple]:
        with self._fs()[0].open_input_stream(partition.path) as f:
            rest = b""
            while block := f.read(1 << 20):
                *lines, rest = (rest + block).split(b"\n")
                yield from map(self._row, filter(None, lines))
            if rest:
                yield self._row(rest)

    @staticmethod
    def _row(line: bytes) -> tuple:
        r = json.loads(line)
        return r["target"], r["anchor"], int(r["hop"]), int(r["iter"]), r.get("text")


class RecordedAnswers(DataSource):
    @classmethod
    def name(cls) -> str:
        return "recorded_answers"

    def schema(self) -> str:
        return SCHEMA

    def reader(self, schema) -> DataSourceReader:
        return _Reader(self.options["path"])


class WordsWithPlaces:
    """Table function: one row (at, word) for each run of a-z."""

    def eval(self, text: str):
        import re

        for i, w in enumerate(re.findall("[a-z]+", (text or "").lower())):
            yield i, w


def register(spark: SparkSession) -> None:
    from pyspark.sql.functions import udtf

    spark.dataSource.register(RecordedAnswers)
    spark.udtf.register("words_with_places", udtf(WordsWithPlaces, returnType="at int, word string"))
