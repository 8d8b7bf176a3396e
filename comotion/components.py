"""Connected components of an edge table, by alternating star contractions."""

from __future__ import annotations

import atexit
import os
import tempfile
import uuid

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

#: Row groups of tables with lists.
_GROUP_BYTES = 8 << 20

_made: list[tuple[SparkSession, str]] = []


def _shared_folder(spark: SparkSession) -> str:
    """The cluster's shared folder. A temporary one only where all executors are threads of this machine and none is set."""
    named = spark.conf.get("spark.checkpoint.dir", None)
    if not named:
        known = spark.sparkContext._jsc.sc().getCheckpointDir()
        named = known.get() if known.isDefined() else None
    if not named:
        master = spark.sparkContext.master
        if master != "local" and not master.startswith("local["):
            raise RuntimeError("spark.checkpoint.dir names no folder that all executors share")
        named = os.path.join(tempfile.gettempdir(), "comotion-checkpoints")
    return named.rstrip("/")


def _sweep() -> None:
    for spark, path in _made:
        try:
            jvm = spark.sparkContext._jvm
            place = jvm.org.apache.hadoop.fs.Path(path)
            place.getFileSystem(spark.sparkContext._jsc.hadoopConfiguration()).delete(place, True)
        except Exception:  # the session has ended: nothing is left to ask
            return


atexit.register(_sweep)


def cut(df: DataFrame, group_bytes: int | None = None) -> DataFrame:
    """Cuts lineage: writes a table into the shared folder and reads it back. Removed when Python ends."""
    path = f"{_shared_folder(df.sparkSession)}/comotion-{uuid.uuid4().hex}"
    _made.append((df.sparkSession, path))
    out = df.write.option("compression", "zstd")
    if group_bytes:
        out = out.option("parquet.block.size", group_bytes)
    out.parquet(path)
    return df.sparkSession.read.schema(df.schema).parquet(path)


def cut_lists(df: DataFrame) -> DataFrame:
    """``cut`` for long lists that shrink much in a file: Spark reads thousands of rows at once, but none beyond a row group."""
    return cut(df, _GROUP_BYTES)


def _stars(edges: DataFrame) -> bool:
    """Whether every larger end of an edge has that edge alone: a further round would change nothing."""
    ends = edges.select(F.col("a").alias("u"), F.lit(1).alias("up")).union(edges.select(F.col("b").alias("u"), F.lit(0).alias("up")))
    return ends.groupBy("u").agg(F.sum("up").alias("n_up"), F.count("*").alias("n")).filter("n_up > 0 and n > 1").isEmpty()


def connected(edges: DataFrame, a: str = "a", b: str = "b", max_rounds: int = 60) -> DataFrame:
    """(node, component) for every node of ``edges`` (two bigint columns); a component is named by its least node.

    Each round hooks all neighbours of a node onto its least neighbour, first those that are larger than the node
    (large star), then the others (small star), until every component is a star around its least node. Least neighbours
    come from a partial aggregate, so that a node of very high degree is never gathered in one place. Nodes without an
    edge don't appear.
    """
    pair = lambda df: df.filter("a <> b").select(F.greatest("a", "b").alias("a"), F.least("a", "b").alias("b")).distinct()
    now = cut(pair(edges.select(F.col(a).cast("long").alias("a"), F.col(b).cast("long").alias("b")).dropna()))
    for _ in range(max_rounds):
        both = now.select(F.col("a").alias("u"), F.col("b").alias("v")).union(now.select(F.col("b").alias("u"), F.col("a").alias("v")))
        # a table of its own, so that Spark may split the join at a node of very high degree
        least = cut(both.groupBy("u").agg(F.min("v").alias("m")).select("u", F.least("m", "u").alias("m")))
        large = both.filter("v > u").join(least, "u").select(F.col("v").alias("a"), F.col("m").alias("b"))
        large = large.filter("a <> b").distinct()
        down = large.groupBy("a").agg(F.min("b").alias("m"))
        small = large.join(down, "a").select(F.explode(F.array(F.struct(F.col("b").alias("a"), F.col("m").alias("b")), F.struct(F.col("a"), F.col("m").alias("b")))).alias("e")).select("e.*")
        now = cut(pair(small))
        if _stars(now):
            break
    else:
        raise RuntimeError("components did not settle")
    labels = now.groupBy("a").agg(F.min("b").alias("component"))
    roots = labels.select(F.col("component").alias("node")).distinct()
    return labels.select(F.col("a").alias("node"), "component").union(roots.select("node", F.col("node").alias("component")))
