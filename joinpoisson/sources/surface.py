"""SQL surface: table functions and a data source that samples joins."""

from __future__ import annotations

from collections.abc import Iterator

from pyspark.sql import SparkSession
from pyspark.sql.datasource import DataSource, DataSourceReader, InputPartition
from pyspark.sql.functions import udtf

from joinpoisson.functions.rng import geometric_value, u01_value


@udtf(returnType="rank: long")
class GeometricRanks:
    """geometric_ranks(n, p, seed): of 1..n each with probability p, by jumps."""

    def eval(self, n: int, p: float, seed: int) -> Iterator[tuple[int]]:
        place, turn = 0, 0
        while True:
            turn += 1
            place += geometric_value(u01_value(seed, "udtf", turn), p, n) + 1
            if place > n:
                return
            yield (place,)


def register_sql(spark: SparkSession) -> None:
    spark.udtf.register("geometric_ranks", GeometricRanks)


class RankSource(DataSource):
    """format("skip_ranks") with options n, p, seed, chunks: the same kind of draw, a partition per chunk of ranks."""

    @classmethod
    def name(cls) -> str:
        return "skip_ranks"

    def schema(self) -> str:
        return "rank long"

    def reader(self, schema) -> DataSourceReader:
        return RankReader(self.options)


class RankReader(DataSourceReader):
    def __init__(self, options):
        self.n, self.p, self.seed, self.chunks = int(options["n"]), float(options["p"]), int(options["seed"]), int(options.get("chunks", "4"))

    def partitions(self) -> list[InputPartition]:
        return [InputPartition(i) for i in range(self.chunks)]

    def read(self, partition: InputPartition) -> Iterator[tuple[int]]:
        i = partition.value
        begin, end = self.n * i // self.chunks, self.n * (i + 1) // self.chunks
        place, turn = 0, 0
        while True:
            turn += 1
            place += geometric_value(u01_value(self.seed, "source", i, turn), self.p, self.n) + 1
            if begin + place > end:
                return
            yield (begin + place,)
