"""Readers and writers: a mesh data source, text meshes, and the tables of a compressed matrix."""

from __future__ import annotations

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F
from pyspark.sql.datasource import DataSource, DataSourceReader, InputPartition

MESH = "pid long, v0 long, v1 long, v2 long, ax double, ay double, az double, bx double, by double, bz double, cx double, cy double, cz double"


EACH = 1 << 20


class _Range(InputPartition):
    def __init__(self, first: int, last: int):
        self.first, self.last = first, last


class _MeshReader(DataSourceReader):
    def __init__(self, n: int):
        self.n = n

    def partitions(self):
        """Ranges of panels: at least one an octant, at most EACH panels."""
        total = 8 * self.n * self.n
        parts = 8 * max(1, -(-total // (8 * EACH)))
        return [_Range(total * k // parts, total * (k + 1) // parts) for k in range(parts)]

    def read(self, partition):
        from panelspark.operators.geometry import decoded_panels

        names = [c.split()[0] for c in MESH.split(", ")]
        for lo in range(partition.first, partition.last, 1 << 14):
            pid = np.arange(lo, min(lo + (1 << 14), partition.last))
            ids, x = decoded_panels(pid, self.n)
            yield pa.RecordBatch.from_arrays([pa.array(pid), *(pa.array(np.ascontiguousarray(ids[:, k])) for k in range(3)), *(pa.array(np.ascontiguousarray(x[:, k, a])) for k in range(3) for a in range(3))], names)


class SphereMesh(DataSource):
    """spark.read.format("sphere_mesh").option("n", 8).load(): Arrow batches, partitions by ranges of panels."""

    @classmethod
    def name(cls):
        return "sphere_mesh"

    def schema(self):
        return MESH

    def reader(self, schema):
        return _MeshReader(int(self.options.get("n", "4")))


def register(spark: SparkSession) -> None:
    spark.dataSource.register(SphereMesh)


def read_off(spark: SparkSession, path: str) -> DataFrame:
    """A text mesh: lines 'v id x y z' and 't id v0 v1 v2'; panels get their corners by three joins on vertex ids."""
    rows = spark.read.text(path).select(F.split(F.trim("value"), r"\s+").alias("f"))
    v = rows.where("f[0] = 'v'").select(F.col("f")[1].cast("long").alias("vid"), *[F.col("f")[k + 2].cast("double").alias(a) for k, a in enumerate("xyz")])
    t = rows.where("f[0] = 't'").select(F.col("f")[1].cast("long").alias("pid"), *[F.col("f")[k + 2].cast("long").alias(f"v{k}") for k in range(3)])
    for k, p in enumerate("abc"):
        t = t.join(v.select(F.col("vid").alias(f"v{k}"), *[F.col(a).alias(f"{p}{a}") for a in "xyz"]), f"v{k}")
    return t.select(*[c.split()[0] for c in MESH.split(", ")])


def write_off(panels: DataFrame, path: str) -> None:
    from ..operators.geometry import vertices

    v = vertices(panels).select(F.concat_ws(" ", F.lit("v"), "vid", "x", "y", "z").alias("value"))
    t = panels.select(F.concat_ws(" ", F.lit("t"), "pid", "v0", "v1", "v2").alias("value"))
    v.unionByName(t).write.mode("overwrite").text(path)


def save_blocks(blocks: DataFrame, path: str) -> None:
    """Blocks partitioned by kind and level, so that scans of either prune."""
    blocks.write.mode("overwrite").partitionBy("kind", "level").parquet(path)


def write_mesh(panels: DataFrame, path: str, form: str) -> None:
    """The mesh columns of panels as csv (with a header), json or parquet."""
    rows = panels.select(*[c.split()[0] for c in MESH.split(", ")])
    (rows.write.mode("overwrite").option("header", True) if form == "csv" else rows.write.mode("overwrite")).format(form).save(path)


def read_mesh(spark: SparkSession, path: str, form: str) -> DataFrame:
    reader = spark.read.schema(MESH).format(form)
    return (reader.option("header", True) if form == "csv" else reader).load(path)


def save_bucketed(rows: DataFrame, name: str, key: str, buckets: int) -> None:
    """A table bucketed and sorted by a cluster column: joins of two such tables by it need no shuffle."""
    rows.write.mode("overwrite").bucketBy(buckets, key).sortBy(key).saveAsTable(name)
