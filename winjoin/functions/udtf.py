"""The block kernel for SQL: SELECT * FROM window_pairs(TABLE(t) PARTITION BY pid ORDER BY (t, stream, id))."""

from __future__ import annotations

from pyspark.sql import SparkSession
from pyspark.sql.functions import udtf

from winjoin.operators.block_kernel import PAIR, BlockWindow


def register_window_pairs(spark: SparkSession, w1: int, w2: int, block: int = 64, name: str = "window_pairs") -> None:
    """Registers a table function over rows (pid, stream 1 or 2, id, key, t); both windows are fixed with the registration."""

    class WindowPairs:
        def __init__(self):
            self.window = BlockWindow((w1, w2), block)

        def eval(self, row):
            self.window.arrive(row["stream"] - 1, row["key"], row["t"], row["id"])
            yield from (tuple(int(x) for x in p) for p in self.window.take())

        def terminate(self):
            self.window.end_of_run()
            yield from (tuple(int(x) for x in p) for p in self.window.take())

    spark.udtf.register(name, udtf(WindowPairs, returnType=PAIR))
