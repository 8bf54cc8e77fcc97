"""Tables as streams: normalised tuples (id, key, t), merged streams, files for replay, sinks."""

from __future__ import annotations

from collections.abc import Sequence

from pyspark.sql import Column, DataFrame, SparkSession, Window
from pyspark.sql import functions as F


def table(spark: SparkSession, sf_dir: str, name: str) -> DataFrame:
    return spark.read.parquet(f"{sf_dir}/{name}.parquet")


def micros(ts: str) -> Column:
    """Microseconds since 1970 of a timestamp without zone; no session setting plays a part."""
    return F.expr(f"timestampdiff(MICROSECOND, TIMESTAMP_NTZ'1970-01-01 00:00:00', `{ts}`)")


def as_stream(df: DataFrame, key: str | Column, time: str | Column, ident: str, payload: Sequence[str] = ()) -> DataFrame:
    """Normalised tuples (id, key, t[, payload]). Rows without key or time never match and go.

    A timestamp column becomes microseconds; an integral time is a logical clock
    and stays. The payload is a struct of the named columns.
    """
    kinds = dict(df.dtypes)
    clock = time
    if isinstance(time, str):
        kind = kinds[time]
        if kind == "timestamp_ntz":
            clock = micros(time)
        elif kind == "timestamp":
            clock = F.unix_micros(F.col(time))
        elif kind == "date":
            clock = F.unix_date(F.col(time)).cast("long") * F.lit(86_400_000_000)
        else:
            clock = F.col(time).cast("long")
    out = [F.col(ident).alias("id"), (F.col(key) if isinstance(key, str) else key).alias("key"), clock.alias("t")]
    if payload:
        out.append(F.struct(*payload).alias("payload"))
    return df.select(*out).where(F.col("key").isNotNull() & F.col("t").isNotNull())


def rejected(df: DataFrame, key: str, time: str) -> DataFrame:
    """The rows that as_stream leaves out, for a side output."""
    return df.where(F.col(key).isNull() | F.col(time).isNull())


def events(spark: SparkSession, sf_dir: str, kind: str) -> DataFrame:
    return as_stream(table(spark, sf_dir, "events").where(F.col("event_type") == kind), "user_id", "ts", "event_id")


def merge_tagged(streams: Sequence[DataFrame]) -> DataFrame:
    """One stream of all, each tuple with the number of its source."""
    out = [s.select(F.lit(i + 1).cast("int").alias("stream"), "id", "key", "t") for i, s in enumerate(streams)]
    merged = out[0]
    for s in out[1:]:
        merged = merged.unionByName(s)
    return merged


def punctuated(merged: DataFrame, by: Sequence[str]) -> DataFrame:
    """A merged stream as runs: before each run of one source within ``by``, a mark row names it; tuples lose their tag.

    Rows (by, seq, mark, id, key, t): mark is set on mark rows alone. Order is (t, stream, id).
    """
    order = Window.partitionBy(*by).orderBy("t", "stream", "id")
    seq = merged.withColumn("seq", F.row_number().over(order) * 2).withColumn("_before", F.lag("stream").over(order))
    opens = F.col("_before").isNull() | (F.col("_before") != F.col("stream"))
    rows = seq.select(*by, "seq", F.lit(None).cast("int").alias("mark"), "id", "key", "t")
    marks = seq.where(opens).select(*by, (F.col("seq") - 1).alias("seq"), F.col("stream").alias("mark"), *(F.lit(None).cast(seq.schema[c].dataType).alias(c) for c in ("id", "key", "t")))
    return rows.unionByName(marks)


def decode_punctuated(rows: DataFrame, by: Sequence[str]) -> DataFrame:
    """Tags restored from marks: (by, stream, id, key, t)."""
    order = Window.partitionBy(*by).orderBy("seq").rowsBetween(Window.unboundedPreceding, Window.currentRow)
    tagged = rows.withColumn("stream", F.last("mark", ignorenulls=True).over(order))
    return tagged.where(F.col("mark").isNull()).select(*by, "stream", "id", "key", "t")


def write_replay_files(df: DataFrame, path: str, n_files: int, time: str = "t") -> None:
    """A table cut by time into files whose names and times follow that order, so a file stream replays it.

    Each file is written by an append of its own: a file stream reads in the order of modification.
    """
    bounds = df.agg(F.min(time).alias("a"), F.max(time).alias("b")).first()
    if bounds.a is None:
        df.limit(0).write.mode("append").parquet(path)
        return
    width = max(1, -(-(bounds.b - bounds.a + 1) // n_files))
    for i in range(n_files):
        low = bounds.a + i * width
        df.where(F.col(time).between(low, low + width - 1)).coalesce(1).write.mode("append").parquet(path)


def replay(spark: SparkSession, path: str, schema, files_per_trigger: int = 1) -> DataFrame:
    """A file stream over time-ordered files."""
    return spark.readStream.schema(schema).option("maxFilesPerTrigger", files_per_trigger).parquet(path)


def rate(spark: SparkSession, rows_per_batch: int = 100, micro_batch: bool = True) -> DataFrame:
    """A synthetic pushed stream (timestamp, value)."""
    if micro_batch:
        return spark.readStream.format("rate-micro-batch").option("rowsPerBatch", rows_per_batch).load()
    return spark.readStream.format("rate").option("rowsPerSecond", rows_per_batch).load()


def write_layout(df: DataFrame, path: str, n_part: int, slab_us: int, key_kind: str = "bigint") -> None:
    """Tuples on disk by time slab and, within it, by partition: replay reads only the slabs it needs and prunes by both."""
    from winjoin.functions.hashing import partition_id

    laid = df.withColumn("slab", F.floor(F.col("t") / slab_us).cast("long")).withColumn("pid", partition_id(F.col("key"), n_part, key_kind))
    laid.repartition("slab", "pid").sortWithinPartitions("slab", "pid", "key", "t").write.mode("overwrite").partitionBy("slab").parquet(path)


def save_bucketed(df: DataFrame, name: str, n: int) -> None:
    """Tuples as a table bucketed and sorted by key: joins of two such tables need no exchange."""
    df.write.mode("overwrite").bucketBy(n, "key").sortBy("key", "t").saveAsTable(name)
