"""Reading and writing samples and convoys, and a Python data source for line files of positions."""

from __future__ import annotations

import io
import uuid

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F
from pyspark.sql.datasource import DataSource, DataSourceReader, InputPartition

from comotion.components import _made, _shared_folder
from comotion.model import SAMPLES


def scratch(spark: SparkSession) -> str:
    """A new folder below the shared one, removed when Python ends."""
    path = f"{_shared_folder(spark)}/comotion-{uuid.uuid4().hex}"
    _made.append((spark, path))
    return path


def round_trip(samples: DataFrame, kind: str) -> DataFrame:
    """Writes samples as csv, json, orc or parquet and reads them back under the fixed schema."""
    spark, path = samples.sparkSession, scratch(samples.sparkSession)
    samples.select("oid", "t", "x", "y").write.format(kind).save(path)
    return spark.read.schema(SAMPLES).format(kind).load(path)


def read_lines(spark: SparkSession, path: str) -> DataFrame:
    """Samples from text files of lines 'object;tick;x;y' on any store; other lines are skipped."""
    part = F.split("value", ";")
    number = lambda k, kind: F.expr(f"try_cast(trim(split(value, ';')[{k}]) as {kind})")
    rows = spark.read.text(path).filter(F.size(part) == 4)
    return rows.select(number(0, "long").alias("oid"), number(1, "long").alias("t"), number(2, "double").alias("x"), number(3, "double").alias("y")).dropna()


def text_round_trip(samples: DataFrame) -> DataFrame:
    """Writes samples as lines of text and reads them back."""
    path = scratch(samples.sparkSession)
    samples.select(F.concat_ws(";", *(F.col(c).cast("string") for c in ("oid", "t", "x", "y"))).alias("value")).write.text(path)
    return read_lines(samples.sparkSession, path)


def track_round_trip(samples: DataFrame) -> DataFrame:
    """Writes samples as lines of text and reads the files through the ``track_lines`` data source."""
    spark, path = samples.sparkSession, scratch(samples.sparkSession)
    samples.select(F.concat_ws(";", *(F.col(c).cast("string") for c in ("oid", "t", "x", "y"))).alias("value")).write.text(path)
    spark.dataSource.register(TrackLines)
    return spark.read.format("track_lines").option("paths", ";".join(spark.read.text(path).inputFiles())).load()


def write_blocks(samples: DataFrame, path: str, ticks: int) -> None:
    """One folder for each block of ticks, sorted by object and time inside."""
    rows = samples.withColumn("block", F.floor(F.col("t") / ticks).cast("long"))
    rows.repartition("block").sortWithinPartitions("block", "oid", "t").write.partitionBy("block").parquet(path)


def write_convoys(convoys: DataFrame, path: str, kind: str = "parquet") -> None:
    """Parquet keeps the member array; csv has a row for each member."""
    if kind == "csv":
        convoys.select(F.explode("members").alias("oid"), "t_start", "t_end").write.csv(path, header=True)
    else:
        convoys.write.parquet(path)


class TrackPartition(InputPartition):
    def __init__(self, path: str):
        self.path = path


class TrackReader(DataSourceReader):
    def __init__(self, options: dict):
        self.paths = [p for p in options.get("paths", options.get("path", "")).split(";") if p]

    def partitions(self):
        return [TrackPartition(p) for p in self.paths]

    def read(self, partition):
        from pyarrow.fs import FileSystem

        store, path = FileSystem.from_uri(partition.path)
        with store.open_input_stream(path) as stream, io.TextIOWrapper(stream, encoding="utf-8") as lines:
            for line in lines:
                parts = line.strip().split(";")
                if len(parts) == 4:
                    yield int(parts[0]), int(parts[1]), float(parts[2]), float(parts[3])


class TrackLines(DataSource):
    """``spark.read.format("track_lines").option("paths", "a;b")``: lines 'object;tick;x;y', lines with another number of fields are skipped. Paths or URIs of any store that Arrow reads; a file is a task."""

    @classmethod
    def name(cls) -> str:
        return "track_lines"

    def schema(self) -> str:
        return SAMPLES

    def reader(self, schema):
        return TrackReader(self.options)
