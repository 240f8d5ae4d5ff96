"""A batch source for transcripts kept as one text file a meeting, lines `SPEAKER<tab>text`.

    spark.dataSource.register(TranscriptSource)
    spark.read.format("transcripts").load("/folder")

The source lists and opens files itself, so it is for folders that every node sees; meetings in other stores are read
by spark.read.text. Each file is a partition of its own up to `files_per_partition`.
"""

from __future__ import annotations

import os
from collections.abc import Iterator

from pyspark.sql.datasource import DataSource, DataSourceReader, InputPartition

SCHEMA = "meeting_id string, utt_no bigint, speaker string, text string"


class Files(InputPartition):
    def __init__(self, paths: list[str]):
        self.paths = paths


class TranscriptReader(DataSourceReader):
    def __init__(self, options: dict):
        if "path" not in options:
            raise ValueError("transcripts needs a path")
        self.path, self.size = options["path"], int(options.get("files_per_partition", 64))

    def partitions(self) -> list[InputPartition]:
        paths = sorted(os.path.join(self.path, f) for f in os.listdir(self.path) if f.endswith(".txt"))
        return [Files(paths[i:i + self.size]) for i in range(0, len(paths), self.size)] or [Files([])]

    def read(self, partition: InputPartition) -> Iterator[tuple]:
        for path in partition.paths:
            meeting = os.path.basename(path)[:-4]
            with open(path, encoding="utf-8") as lines:
                for i, line in enumerate(x.rstrip("\n") for x in lines):
                    speaker, _, text = line.rpartition("\t") if "\t" not in line else line.partition("\t")
                    yield meeting, i, speaker or None, text


class TranscriptSource(DataSource):
    @classmethod
    def name(cls) -> str:
        return "transcripts"

    def schema(self) -> str:
        return SCHEMA

    def reader(self, schema) -> DataSourceReader:
        return TranscriptReader(dict(self.options))
