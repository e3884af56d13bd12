"""The generated families as a Spark data source: spark.read.format('text_family').option('ks', '4,8').load()."""

from __future__ import annotations

from collections.abc import Iterator

from pyspark.sql.datasource import DataSource, DataSourceReader, InputPartition


def four_letter(k: int) -> str:
    """The lower-bound text of size k; see workloads.family."""
    block = lambda i: "a" * i + "bb" + "a" * (k - i)
    parts = ["a" * i + "c" * i for i in range(2, k + 1)]
    parts += ["a" * i + "bb" for i in range(k)]
    parts += [block(i) + "d" * (i + 2) for i in range(k + 1)]
    word = "".join(block(k) + block(k - i) for i in range(1, k // 2)) + block(k) + "a" * (k - 1)
    return "".join(parts) + word * (k // 2)


class _Size(InputPartition):
    def __init__(self, k: int):
        self.k = k


class _Reader(DataSourceReader):
    def __init__(self, options):
        self.kind = options.get("kind", "four_letter")
        self.ks = [int(x) for x in options.get("ks", "4,8,16").split(",")]

    def partitions(self) -> list[InputPartition]:
        return [_Size(k) for k in self.ks]

    def read(self, partition: _Size) -> Iterator[tuple]:
        k = partition.k
        yield k, four_letter(k) if self.kind == "four_letter" else "a" * (2 ** (k + 1) - 2)


class FamilySource(DataSource):
    """One partition for each size; kind is four_letter or unary."""

    @classmethod
    def name(cls) -> str:
        return "text_family"

    def schema(self) -> str:
        return "id int, text string"

    def reader(self, schema) -> DataSourceReader:
        return _Reader(self.options)
