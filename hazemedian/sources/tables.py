"""Scans and sinks: pruned table reads, point files, streams of slices, planted instances, versioned snapshots."""

from __future__ import annotations

import json
import tempfile
import uuid
from collections.abc import Iterator
from contextlib import contextmanager

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F
from pyspark.sql.datasource import DataSource, DataSourceReader, InputPartition


#: Bytes of a message between the JVM and a Python task that reads a large input.
BATCH_BYTES = 8 << 20
#: Versions of a snapshot that stay, for readers of the ones before the newest.
KEPT_VERSIONS = 3


def table(spark: SparkSession, sf_dir: str, name: str, *columns: str) -> DataFrame:
    df = spark.read.parquet(f"{sf_dir}/{name}.parquet")
    return df.select(*columns) if columns else df


def shared_folder(spark: SparkSession) -> str:
    """A new folder under the cluster's shared one; a local one only in local mode, where none is needed."""
    root = spark.conf.get("spark.checkpoint.dir", None)
    if not root:
        if not spark.sparkContext.master.startswith("local") or spark.sparkContext.master.startswith("local-cluster"):
            raise ValueError("set spark.checkpoint.dir to a folder that the driver and all executors share")
        root = tempfile.mkdtemp(prefix="hazemedian-")
    return f"{root.rstrip('/')}/hazemedian-{uuid.uuid4().hex}"


@contextmanager
def small_batches(spark: SparkSession, most: int) -> Iterator[None]:
    """Jobs started inside send at most `most` bytes at once to their Python tasks, or one row."""
    name = "spark.sql.execution.arrow.maxBytesPerBatch"
    old = spark.conf.get(name)
    spark.conf.set(name, f"{most}b")
    try:
        yield
    finally:
        spark.conf.set(name, old)


def kept(df: DataFrame, label: str = "kept", **options: str) -> DataFrame:
    """`df` written to the shared folder and read again: cuts lineage and outlives lost executors."""
    path = f"{shared_folder(df.sparkSession)}-{label}"
    df.write.options(**options).parquet(path)
    return df.sparkSession.read.schema(df.schema).parquet(path)


def points(spark: SparkSession, path: str, kind: str, schema: str, coords: list[str]) -> DataFrame:
    """Points of csv, json, orc, parquet or text files (text: blanks or commas between numbers) with a `coords` array."""
    if kind == "text":
        numbers = F.transform(F.split(F.trim("value"), r"[,\s]+"), lambda x: x.cast("double"))
        return spark.read.text(path).select(numbers.alias("coords"))
    return spark.read.format(kind).schema(schema).load(path).withColumn("coords", F.array(*(F.col(c).cast("double") for c in coords)))


def write_snapshot(df: DataFrame, folder: str, version: int) -> None:
    """Writes a version beside the older ones, then a pointer to it; a reader sees a whole version or the one before."""
    spark = df.sparkSession
    df.write.mode("overwrite").parquet(f"{folder}/v={version}")
    spark.createDataFrame([(json.dumps({"version": version}),)], "value string").coalesce(1).write.mode("overwrite").text(f"{folder}/_pointers/{version:012d}")
    path = spark._jvm.org.apache.hadoop.fs.Path
    fs = path(folder).getFileSystem(spark._jsc.hadoopConfiguration())
    for old in sorted(int(x.getPath().getName()) for x in fs.listStatus(path(f"{folder}/_pointers")))[:-KEPT_VERSIONS]:
        fs.delete(path(f"{folder}/_pointers/{old:012d}"), True)
        fs.delete(path(f"{folder}/v={old}"), True)


def read_snapshot(spark: SparkSession, folder: str) -> tuple[int, DataFrame | None]:
    """(version, rows) of the newest complete version; (-1, None) if there is none."""
    path = spark._jvm.org.apache.hadoop.fs.Path(f"{folder}/_pointers")
    fs = path.getFileSystem(spark._jsc.hadoopConfiguration())
    if not fs.exists(path):
        return -1, None
    found = [int(x.getPath().getName()) for x in fs.listStatus(path) if fs.exists(spark._jvm.org.apache.hadoop.fs.Path(x.getPath(), "_SUCCESS"))]
    return (max(found), spark.read.parquet(f"{folder}/v={max(found)}")) if found else (-1, None)


class PlantedNodes(DataSource):
    """`planted_nodes`: nodes of ten uniform locations round `groups` far centres of dimension `d`; options n, d, groups, seed, parts."""

    @classmethod
    def name(cls) -> str:
        return "planted_nodes"

    def schema(self) -> str:
        from ..model import NODES

        return NODES + ", planted int"

    def reader(self, schema):
        return _PlantedReader(self.options)


class _PlantedReader(DataSourceReader):
    def __init__(self, options):
        self.n, self.d, self.groups, self.seed, self.parts = (int(options.get(k, v)) for k, v in (("n", "1000"), ("d", "2"), ("groups", "5"), ("seed", "1"), ("parts", "4")))

    def partitions(self):
        return [InputPartition(k) for k in range(self.parts)]

    def read(self, partition):
        import numpy as np

        for i in range(partition.value, self.n, self.parts):
            rng = np.random.default_rng([self.seed, i])
            g = i % self.groups
            middle = np.array([100.0 * (g % 3), 100.0 * (g // 3)] + [0.0] * (self.d - 2))[: self.d]
            x = middle + rng.normal(0, 1, self.d) + rng.normal(0, 0.5, (10, self.d))
            yield i, 1.0, 1.0, [(10 * i + j, p.tolist(), 0.1) for j, p in enumerate(x)], g
