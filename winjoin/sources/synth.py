"""Streams by rule: Poisson arrivals with b-model keys, reproducible whatever the partitioning."""

from __future__ import annotations

from collections.abc import Iterator

from pyspark.sql import Column, DataFrame, SparkSession, Window
from pyspark.sql import functions as F
from pyspark.sql.datasource import DataSource, DataSourceReader, InputPartition, SimpleDataSourceStreamReader

from winjoin.functions.hashing import bmodel_key, mix32_int, uniform

CHUNK = 1 << 16


def gap_us(ident: Column, rate: float, seed: int = 0) -> Column:
    """An exponential gap in whole microseconds, for the tuple of this number."""
    return F.round(-F.log(uniform(ident + F.lit(seed * 1_000_003 + 7))) / F.lit(rate) * F.lit(1e6)).cast("long")


def poisson_stream(spark: SparkSession, rate: float, seconds: float, b: float = 0.7, seed: int = 42, domain: int = 10_000_001) -> DataFrame:
    """Tuples (id, key, t, payload of 40 bytes) of a Poisson stream, t from 0.

    Times are sums of gaps: within chunks of consecutive numbers, then over the
    chunks, so no window holds the whole stream in one task but the one over chunk totals.
    """
    n = int(rate * seconds + 6 * (rate * seconds) ** 0.5) + 10
    rows = spark.range(n).select("id", (F.col("id") / CHUNK).cast("long").alias("chunk"), gap_us(F.col("id"), rate, seed).alias("gap"))
    totals = rows.groupBy("chunk").agg(F.sum("gap").alias("total"))
    before = totals.select("chunk", (F.sum("total").over(Window.orderBy("chunk")) - F.col("total")).alias("offset"))
    within = F.sum("gap").over(Window.partitionBy("chunk").orderBy("id"))
    timed = rows.withColumn("inner", within).join(before, "chunk").select("id", (F.col("offset") + F.col("inner")).alias("t"))
    keyed = timed.select("id", bmodel_key(F.col("id"), b, domain=domain, seed=seed * 100_003).alias("key"), "t", F.lpad(F.col("id").cast("string"), 40, "0").alias("payload"))
    return keyed.where(F.col("t") < F.lit(int(seconds * 1e6)))


def compress(stream: DataFrame, factor: float) -> DataFrame:
    """The same tuples in 1/factor of the time: the rate rises by the factor."""
    return stream.withColumn("t", F.floor(F.col("t") / F.lit(factor)).cast("long"))


def thin(stream: DataFrame, keep: float, seed: int = 0) -> DataFrame:
    """A share of the tuples, by a hash of their numbers: the rate falls, time stays. Also the load-shedding baseline."""
    return stream.where(uniform(F.col("id") * F.lit(2) + F.lit(seed * 2 + 1)) < F.lit(keep))


class _Range(InputPartition):
    def __init__(self, low: int, high: int):
        super().__init__((low, high))
        self.low, self.high = low, high


def _tuples(options: dict, low: int, high: int) -> Iterator[tuple]:
    """Tuples by number, evenly spaced in time: the n-th at n / rate seconds."""
    b, rate, seed = float(options.get("b", 0.7)), float(options.get("rate", 1500)), int(options.get("seed", 42))
    bound = int(b * (1 << 32))
    for i in range(low, high):
        x = 0
        for j in range(24):
            x = x * 2 + (mix32_int((i + seed * 100_003) * 32 + j) < bound)
        yield i, x * 10_000_001 >> 24, int(i * 1e6 / rate)


class _Batch(DataSourceReader):
    def __init__(self, options: dict):
        self.options = options

    def partitions(self) -> list[InputPartition]:
        n, parts = int(self.options.get("n", 1000)), int(self.options.get("partitions", 4))
        step = -(-n // parts)
        return [_Range(a, min(a + step, n)) for a in range(0, n, step)]

    def read(self, partition: _Range) -> Iterator[tuple]:
        return _tuples(self.options, partition.low, partition.high)


class _Stream(SimpleDataSourceStreamReader):
    def __init__(self, options: dict):
        self.options = options

    def initialOffset(self) -> dict:
        return {"n": 0}

    def read(self, start: dict) -> tuple[Iterator[tuple], dict]:
        end = min(start["n"] + int(self.options.get("rowsPerBatch", 500)), int(self.options.get("n", 1000)))
        return iter(list(_tuples(self.options, start["n"], end))), {"n": end}

    def readBetweenOffsets(self, start: dict, end: dict) -> Iterator[tuple]:
        return iter(list(_tuples(self.options, start["n"], end["n"])))


class BModelSource(DataSource):
    """format('bmodel'): tuples (id, key, t) for batch and stream reads; options n, b, rate, seed, rowsPerBatch."""

    @classmethod
    def name(cls) -> str:
        return "bmodel"

    def schema(self) -> str:
        return "id long, key long, t long"

    def reader(self, schema) -> DataSourceReader:
        return _Batch(self.options)

    def simpleStreamReader(self, schema) -> SimpleDataSourceStreamReader:
        return _Stream(self.options)
