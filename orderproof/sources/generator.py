"""A data source that makes register histories of any size: spark.read.format("register_history").option("rows", n).load()."""

from __future__ import annotations

from pyspark.sql import SparkSession
from pyspark.sql.datasource import DataSource, DataSourceReader, InputPartition

#: Operations of a generated transaction, and microseconds between the begins of two.
BLOCK, GAP = 8, 50


class Part(InputPartition):
    def __init__(self, first: int, last: int):
        self.first, self.last = first, last


class _Reader(DataSourceReader):
    def __init__(self, options):
        self.rows = int(options.get("rows", 80_000))
        self.objects = int(options.get("objects", 10_000))
        self.writers = int(options.get("writers", 5))  # blocks out of ten
        self.parts = int(options.get("partitions", 8))

    def partitions(self):
        blocks = -(-self.rows // BLOCK)
        step = -(-blocks // self.parts) or 1
        return [Part(a, min(a + step, blocks)) for a in range(0, blocks, step)]

    def read(self, part: Part):
        for block in range(part.first, part.last):
            kind = "w" if block * 7 % 10 < self.writers else "r"
            for k in range(BLOCK):
                n = block * BLOCK + k
                if n >= self.rows:
                    return
                s = block * GAP
                yield block + 1, k, kind, f"part:{n * 7919 % self.objects}", n + 1 if kind == "w" else None, s, s + 3 * GAP


class RegisterHistory(DataSource):
    """Requests of read-only and write-only transactions over rows chosen by a rule: (txn_id, op_seq, kind, obj, ver, s, e). Reads have no
    version yet: build.generated() lets them see one."""

    @classmethod
    def name(cls):
        return "register_history"

    def schema(self):
        return "txn_id long, op_seq int, kind string, obj string, ver long, s long, e long"

    def reader(self, schema):
        return _Reader(self.options)


def register(spark: SparkSession) -> None:
    spark.dataSource.register(RegisterHistory)
