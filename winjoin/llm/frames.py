"""Small helpers shared by the operators of this subpackage."""

from __future__ import annotations

import re
import uuid
from collections.abc import Iterable, Iterator

import pyarrow as pa
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F


_CLEANUP = "spark.sql.classic.shuffleDependency.fileCleanup.enabled"


def shared_dir(spark: SparkSession, name: str) -> str:
    """A fresh folder for a written table, below the shared folder of spark.checkpoint.dir.

    Only a session that names none gets one of its own, and only where all of it runs on this machine.
    """
    base = spark.conf.get("spark.checkpoint.dir", None)
    if not base:
        held = spark.sparkContext._jsc.sc().getCheckpointDir()
        if not held.isDefined() and not re.match(r"local(\[[^-]|$)", spark.sparkContext.master):
            raise ValueError("set spark.checkpoint.dir to a folder that driver and executors share")
        base = held.get() if held.isDefined() else "/tmp/winjoin-checkpoints"
    return f"{base.rstrip('/')}/{name}-{uuid.uuid4().hex}"


def materialize(df: DataFrame, name: str, options: dict | None = None) -> DataFrame:
    """Write a frame to the shared folder and read it back: lineage ends there, lost executors lose nothing.

    The shuffle files of the write are deleted once it has ended.
    """
    spark = df.sparkSession
    path, held = shared_dir(spark, name), spark.conf.get(_CLEANUP)
    spark.conf.set(_CLEANUP, "true")
    try:
        df.write.options(**(options or {})).parquet(path)
    finally:
        spark.conf.set(_CLEANUP, held)
    return spark.read.schema(df.schema).parquet(path)


def release(*frames: DataFrame) -> None:
    """Delete the files behind materialized frames that are no longer read."""
    for df in frames:
        spark = df.sparkSession
        jvm = spark.sparkContext._jvm
        for parent in {f.rsplit("/", 1)[0] for f in df.inputFiles()}:
            path = jvm.org.apache.hadoop.fs.Path(parent)
            path.getFileSystem(spark.sparkContext._jsc.hadoopConfiguration()).delete(path, True)


def fresh(columns: Iterable[str], *wanted: str) -> list[str]:
    """The wanted names, each with as many underscores behind it as no column of that name (in any case of letters) needs."""
    taken, out = {c.lower() for c in columns}, []
    for name in wanted:
        while name.lower() in taken:
            name += "_"
        taken.add(name.lower())
        out.append(name)
    return out


def text_of(docs: DataFrame, id_col: str, text_col: str) -> DataFrame:
    """Only the id and the text (null: empty), under names that no other column can clash with."""
    return docs.select(F.col(f"`{id_col}`").alias("doc_id"), F.coalesce(F.col(f"`{text_col}`"), F.lit("")).alias("text"))


class Forest:
    """Union-find over what a task has met; keeps the links that connect something new. Memory is bounded by forgetting."""

    def __init__(self, most: int = 1_000_000):
        self.parent: dict = {}
        self.most = most

    def root(self, x):
        parent = self.parent
        while (up := parent.setdefault(x, x)) != x:
            parent[x] = x = parent.get(up, up)
        return x

    def fresh(self, links: Iterable[tuple]) -> list[tuple]:
        if len(self.parent) > self.most:
            self.parent.clear()
        out = []
        for x, y in links:
            rx, ry = self.root(x), self.root(y)
            if rx != ry:
                self.parent[ry] = rx
                out.append((x, y))
        return out


def thin(edges: DataFrame) -> DataFrame:
    """An edge list (a, b) with the same components: each task keeps a spanning forest of the edges it reads."""

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        forest = Forest()
        for batch in batches:
            kept = forest.fresh(zip(batch.column(0).to_pylist(), batch.column(1).to_pylist()))
            yield pa.RecordBatch.from_arrays([pa.array([x for x, _ in kept], batch.schema.field(0).type), pa.array([y for _, y in kept], batch.schema.field(1).type)], ["a", "b"])

    return edges.select("a", "b").mapInArrow(run, edges.select("a", "b").schema)


def connected(edges: DataFrame, a: str = "a", b: str = "b", rounds: int = 60) -> DataFrame:
    """Connected components of an edge list: rows (node, root), root the least node of the component.

    Alternates linking every node's greater neighbours to its least one with
    linking all its neighbours to it, until nothing moves. Each round is two
    grouped minima and two joins, so a hub of any degree never meets in one
    task as a list; the edge list is written out between rounds.
    """
    def state(df: DataFrame) -> tuple:
        """Count and checksum of distinct rows."""
        return tuple(df.agg(F.count(F.lit(1)), F.sum(F.xxhash64("u", "v").cast("decimal(20,0)")), F.sum(F.hash("v", "u").cast("long"))).first())

    now = materialize(edges.select(F.greatest(a, b).alias("u"), F.least(a, b).alias("v")).where("u <> v").distinct(), "cc")
    was = state(now)
    for _ in range(rounds):
        # u > v in every row. Large step: a node's neighbours above it move to the least of its neighbourhood.
        both = now.select(F.col("u").alias("x"), F.col("v").alias("y")).unionByName(now.select(F.col("v").alias("x"), F.col("u").alias("y")))
        least = both.groupBy("x").agg(F.min("y").alias("m")).select("x", F.least("x", "m").alias("m"))
        large = both.where("y > x").join(least, "x").select(F.col("y").alias("u"), F.col("m").alias("v"))
        # Small step: neighbours not above a node, and the node itself, move to the least of them.
        down = large.groupBy("u").agg(F.min("v").alias("m"))
        up = large.join(down, "u").where("v <> m").select(F.col("v").alias("u"), F.col("m").alias("v"))
        nxt = materialize(up.unionByName(down.select("u", F.col("m").alias("v"))).distinct(), "cc")
        is_ = state(nxt)
        release(now)
        now = nxt
        if is_ == was:
            break
        was = is_
    else:
        raise RuntimeError(f"components did not settle in {rounds} rounds")
    # a star forest: every u names its root once
    return now.select(F.col("u").alias("node"), F.col("v").alias("root")).unionByName(now.select(F.col("v").alias("node"), F.col("v").alias("root")).distinct())


def bounded_rows(df: DataFrame, most: int, what: str) -> list:
    """Collect a frame whose size is proven: more than ``most`` rows is an error, not a truncation."""
    rows = df.limit(most + 1).collect()
    if len(rows) > most:
        raise ValueError(f"{what}: more than {most} rows")
    return rows
