"""Sinks: file formats, partitioned and bucketed tables, versioned snapshots of a mapping."""

from __future__ import annotations

import uuid

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from neardup.sources.lineage import shared_folder


def scratch(spark: SparkSession) -> str:
    """A fresh folder below the shared one."""
    return f"{shared_folder(spark)}/sink-{uuid.uuid4().hex}"


def round_trip(df: DataFrame, fmt: str) -> DataFrame:
    """``df`` written in a format (parquet, orc, json, csv) and read with its own schema."""
    path = scratch(df.sparkSession)
    options = {"header": "true"} if fmt == "csv" else {}
    df.write.format(fmt).options(**options).save(path)
    return df.sparkSession.read.format(fmt).options(**options).schema(df.schema).load(path)


def text_round_trip(df: DataFrame, column: str) -> DataFrame:
    """One string column as lines of text; line breaks are escaped."""
    path = scratch(df.sparkSession)
    escaped = F.replace(F.replace(F.col(column), F.lit("\\"), F.lit("\\\\")), F.lit("\n"), F.lit("\\n"))
    df.select(escaped.alias("value")).write.text(path)
    return df.sparkSession.read.text(path)


def partitioned(df: DataFrame, by: str) -> DataFrame:
    """``df`` written in folders by a column and read back, so that filters on it prune folders."""
    path = scratch(df.sparkSession)
    df.write.partitionBy(by).parquet(path)
    return df.sparkSession.read.parquet(path)


def bucketed(df: DataFrame, by: str, buckets: int, name: str) -> DataFrame:
    """``df`` as a table bucketed and sorted by a column; joins on it need no shuffle of this side."""
    spark = df.sparkSession
    spark.sql(f"drop table if exists {name}")
    df.write.bucketBy(buckets, by).sortBy(by).format("parquet").mode("overwrite").saveAsTable(name)
    return spark.table(name)


class Snapshots:
    """Versions of a table in a folder with a pointer file: readers see whole versions, a repeated batch id adds none."""

    def __init__(self, spark: SparkSession, root: str):
        self.spark, self.root = spark, root
        self._path = spark._jvm.org.apache.hadoop.fs.Path
        self._fs = self._path(root).getFileSystem(spark.sparkContext._jsc.hadoopConfiguration())
        self._fs.mkdirs(self._path(root))

    def _pointers(self) -> list[tuple[int, str]]:
        names = [s.getPath().getName() for s in self._fs.listStatus(self._path(self.root))]
        return sorted((int(n.split("-")[1]), n.split("-", 2)[2]) for n in names if n.startswith("pointer-"))

    def version(self) -> int:
        """The newest committed version, -1 if none."""
        p = self._pointers()
        return p[-1][0] if p else -1

    def read(self, version: int | None = None) -> DataFrame:
        v = self.version() if version is None else version
        return self.spark.read.parquet(f"{self.root}/v{v}")

    def commit(self, df: DataFrame, batch_id: int | str) -> bool:
        """Writes the next version and then its pointer; false if the batch was committed before."""
        done = self._pointers()
        if any(b == str(batch_id) for _, b in done):
            return False
        v = (done[-1][0] if done else -1) + 1
        df.write.mode("overwrite").parquet(f"{self.root}/v{v}")
        self._fs.create(self._path(f"{self.root}/pointer-{v}-{batch_id}"), False).close()
        return True
