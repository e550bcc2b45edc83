"""A data source of key-value and needle examples: spark.read.format("windowforge_examples"), a partition per block of examples."""

from __future__ import annotations

import hashlib

from pyspark.sql.datasource import DataSource, DataSourceReader, InputPartition


class Block(InputPartition):
    def __init__(self, begin: int, end: int):
        self.begin, self.end = begin, end


class ExamplesReader(DataSourceReader):
    def __init__(self, options):
        self.pairs, self.examples = int(options.get("pairs", 140)), int(options.get("examples", 500))
        self.position, self.block = int(options.get("position", 1)), int(options.get("block", 100))

    def partitions(self):
        return [Block(b, min(b + self.block, self.examples)) for b in range(0, self.examples, self.block)]

    def read(self, partition):
        made = lambda what, e, i: hashlib.md5(f"{what}:{e}:{self.pairs}:{i}".encode()).hexdigest()
        for e in range(partition.begin, partition.end):
            context = " ".join(f"{made('k', e, i)}: {made('v', e, i)}" for i in range(1, self.pairs + 1))
            yield e, self.pairs, self.position, context, made("k", e, self.position), made("v", e, self.position)


class Examples(DataSource):
    @classmethod
    def name(cls):
        return "windowforge_examples"

    def schema(self):
        return "example_id long, n_pairs int, position int, context string, question string, answer string"

    def reader(self, schema):
        return ExamplesReader(self.options)


def register(spark) -> None:
    spark.dataSource.register(Examples)
