"""File sources and sinks, and a replayable stream source of the events table."""

from __future__ import annotations

import json
from collections.abc import Iterator

import pyarrow as pa
import pyarrow.parquet as pq
from pyarrow import fs
from pyspark.sql import Column, DataFrame, SparkSession
from pyspark.sql import functions as F
from pyspark.sql.datasource import DataSource, DataSourceReader, DataSourceStreamReader, InputPartition

from discourselab.session import scratch


def roundtrip(df: DataFrame, fmt: str, partition_by: str | None = None, mode: str = "overwrite", **options: str) -> DataFrame:
    """Write ``df`` in a file format and read it back with its own schema."""
    path = scratch(df.sparkSession, fmt)
    writer = df.write.mode(mode).format(fmt).options(**options)
    (writer.partitionBy(partition_by) if partition_by else writer).save(path)
    return df.sparkSession.read.schema(df.schema).format(fmt).options(**options).load(path).select(*df.columns)


class _Files(InputPartition):
    def __init__(self, paths: list[str]) -> None:
        super().__init__(paths)
        self.paths = paths


class _ReplayReader(DataSourceReader):
    """Rows of written files, which Python reads from the folder that driver and executors share."""

    def __init__(self, options: dict[str, str]) -> None:
        self.files = json.loads(options["files"])

    def partitions(self) -> list[_Files]:
        return [_Files([f]) for f in self.files]

    def read(self, partition: _Files) -> Iterator[pa.RecordBatch]:
        for path in partition.paths:
            found, inside = fs.FileSystem.from_uri(path)
            with found.open_input_file(inside) as f:
                yield from pq.ParquetFile(f).iter_batches(10_000)


class _ReplayStream(DataSourceStreamReader):
    """The same rows as a stream, some files at a time."""

    def __init__(self, options: dict[str, str]) -> None:
        self.batch = _ReplayReader(options)
        self.step = int(options["step"])
        self.until = 0

    def initialOffset(self) -> dict[str, int]:  # noqa: N802
        return {"file": 0}

    def latestOffset(self) -> dict[str, int]:  # noqa: N802
        self.until = min(len(self.batch.files), self.until + self.step)
        return {"file": self.until}

    def partitions(self, start: dict[str, int], end: dict[str, int]) -> list[_Files]:
        self.until = max(self.until, end["file"])
        return [_Files([f]) for f in self.batch.files[start["file"] : end["file"]]]

    def read(self, partition: _Files) -> Iterator[pa.RecordBatch]:
        return self.batch.read(partition)


class ReplaySource(DataSource):
    """Recorded events as a Python data source: ``spark.read.format("replay")``."""

    @classmethod
    def name(cls) -> str:
        return "replay"

    def schema(self) -> str:
        return "event_id long, user_id long, event_type string, value double"

    def reader(self, schema) -> _ReplayReader:  # noqa: ANN001
        return _ReplayReader(self.options)

    def streamReader(self, schema) -> _ReplayStream:  # noqa: ANN001, N802
        return _ReplayStream(self.options)


def _recorded(events: DataFrame, parts: int) -> list[str]:
    """The events, written by Spark to the shared folder in at least ``parts`` files."""
    path = scratch(events.sparkSession, "replay")
    rows = events.select("event_id", "user_id", "event_type", "value")
    rows.repartition(max(parts, rows.rdd.getNumPartitions())).write.parquet(path)
    found = sorted(events.sparkSession.read.parquet(path).inputFiles())
    return [f.replace("file:/", "file:///", 1) if f.startswith("file:/") and not f.startswith("file://") else f for f in found]


def replay(events: DataFrame, parts: int = 4) -> DataFrame:
    spark = events.sparkSession
    spark.dataSource.register(ReplaySource)
    return spark.read.format("replay").option("files", json.dumps(_recorded(events, parts))).load()


def replay_stream(events: DataFrame, batches: int) -> DataFrame:
    spark = events.sparkSession
    spark.dataSource.register(ReplaySource)
    files = _recorded(events, batches)
    return spark.readStream.format("replay").option("files", json.dumps(files)).option("step", max(1, len(files) // batches)).load()


def event_stream(spark: SparkSession, sf_dir: str, batches: int = 1, late: Column | None = None) -> DataFrame:
    """The events table as a stream of files, with ``ts`` as a zoned time so that watermarks apply.

    With more than one batch the events are written in slices of time, and a batch reads one slice. Rows that
    ``late`` names come in a slice of their own at the end, after one that holds only the last of the others.
    """
    path = f"{sf_dir}/events.parquet"
    events = spark.read.parquet(path)
    if batches > 1 or late is not None:
        return _sliced(events, batches, late).withColumn("ts", F.col("ts").cast("timestamp"))
    # a file source watches a folder; a single file is found by its name
    stream = spark.readStream.schema(events.schema)
    found = stream.option("pathGlobFilter", "events.parquet").parquet(sf_dir) if path_is_file(spark, path) else stream.parquet(path)
    return found.withColumn("ts", F.col("ts").cast("timestamp"))


def _sliced(events: DataFrame, batches: int, late: Column | None) -> DataFrame:
    spark, base = events.sparkSession, scratch(events.sparkSession, "stream-in")
    at = F.unix_micros(F.col("ts").cast("timestamp"))
    now = events.where(~late) if late is not None else events
    bounds = now.select(at.alias("t")).approxQuantile("t", [k / batches for k in range(1, batches)], 0.01) if batches > 1 else []
    edges = [None, *bounds, None]
    parts = [now.where((F.lit(True) if a is None else at >= a) & (F.lit(True) if b is None else at < b)) for a, b in zip(edges, edges[1:], strict=False)]
    if late is not None:
        last = now.agg(F.max(at)).first()[0]
        parts = [*parts[:-1], parts[-1].where(at < last), now.where(at == last), events.where(late)]
    for k, part in enumerate(parts):  # files are read in the order in which they were written
        part.coalesce(1).write.parquet(f"{base}/slice={k}")
    return spark.readStream.schema(events.schema).option("maxFilesPerTrigger", 1).parquet(base).select(*events.columns)


def path_is_file(spark: SparkSession, path: str) -> bool:
    hadoop = spark.sparkContext._jvm.org.apache.hadoop.fs.Path(path)
    return hadoop.getFileSystem(spark.sparkContext._jsc.hadoopConfiguration()).getFileStatus(hadoop).isFile()
