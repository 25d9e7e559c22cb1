"""Python data source ``phrasefile``: stored phrases (JSON lines) read back as decoded strings."""

from __future__ import annotations

import json
from collections.abc import Iterator

from pyspark.sql import SparkSession
from pyspark.sql.datasource import DataSource, DataSourceReader, InputPartition


class _Part(InputPartition):
    def __init__(self, path: str):
        self.path = path


class PhraseFileReader(DataSourceReader):
    def __init__(self, paths: list[str]):
        self.paths = paths

    def partitions(self) -> list[_Part]:
        return [_Part(p) for p in self.paths]

    def read(self, part: _Part) -> Iterator[tuple[str, str | None]]:
        from phrasework.kernels.greedy import references, resolve

        with open(part.path, encoding="utf-8") as lines:
            for line in lines:
                row = json.loads(line)
                phrases = [(p["start"] - 1, p["length"], (p.get("ref") or 0) - 1) for p in row["phrases"]]
                literal = {p["start"] - 1: p["literal"] for p in row["phrases"] if p.get("ref") is None}
                n = sum(size for _, size, _ in phrases)
                source, _ = resolve(references(phrases, n))
                yield row["string_id"], None if (source < 0).any() else "".join(literal[s] for s in source.tolist())


class PhraseFile(DataSource):
    """Options: ``path``, a file or comma-separated files of {"string_id", "phrases"} lines that every executor can open."""

    @classmethod
    def name(cls) -> str:
        return "phrasefile"

    def schema(self) -> str:
        return "string_id string, text string"

    def reader(self, schema) -> PhraseFileReader:
        return PhraseFileReader(self.options["path"].split(","))


def register(spark: SparkSession) -> None:
    spark.dataSource.register(PhraseFile)
