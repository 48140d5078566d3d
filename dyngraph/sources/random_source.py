"""spark.read.format("random_gnm"): the random graph generator as a data source."""

from __future__ import annotations

import hashlib

from pyspark.sql.datasource import DataSource, DataSourceReader, InputPartition


class RandomGraphSource(DataSource):
    """Options steps, n, f, seed, parts; rows as of random_gnm before pairs are made distinct."""

    @classmethod
    def name(cls):
        return "random_gnm"

    def schema(self):
        return "t long, src long, dst long, w double"

    def reader(self, schema):
        return _Reader({k: int(v) for k, v in self.options.items() if k in ("steps", "n", "f", "seed", "parts")})


class _Reader(DataSourceReader):
    def __init__(self, o):
        self.o = {"seed": 1, "parts": 4} | o

    def partitions(self):
        return [InputPartition(i) for i in range(self.o["parts"])]

    def read(self, partition):
        o = self.o
        size = o["n"] * o["f"]
        end = lambda i, s: int(hashlib.md5(f"{o['seed']}:{i}:{s}".encode()).hexdigest()[:8], 16) % o["n"]
        for i in range(partition.value, o["steps"] * size, o["parts"]):
            yield i // size + 1, end(i, "s"), end(i, "d"), 1.0
