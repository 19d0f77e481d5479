"""Reading and writing: tables, text formats, timing sinks, the index."""

from __future__ import annotations

import time

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F


def table(spark: SparkSession, sf_dir: str, name: str) -> DataFrame:
    """A given table; whatever is selected and filtered reaches the scan."""
    return spark.read.parquet(f"{sf_dir}/{name}.parquet")


def write_libsvm(vectors: DataFrame, path: str, label: str = "label", features: str = "features") -> None:
    """The sparse text format."""
    vectors.select(F.col(label).alias("label"), F.col(features).alias("features")).write.format("libsvm").mode("overwrite").save(path)


def load_libsvm(spark: SparkSession, path: str, dims: int) -> DataFrame:
    return spark.read.format("libsvm").option("numFeatures", dims).load(path)


def timed(df: DataFrame) -> float:
    """Seconds to compute all rows and columns, kept nowhere."""
    t = time.perf_counter()
    df.write.format("noop").mode("overwrite").save()
    return time.perf_counter() - t


def load_times(spark: SparkSession, vectors: DataFrame, folder: str, dims: int) -> DataFrame:
    """One row: seconds to load the same vectors from text and from Parquet."""
    write_libsvm(vectors, f"{folder}/text")
    vectors.write.mode("overwrite").parquet(f"{folder}/binary")
    text, binary = timed(load_libsvm(spark, f"{folder}/text", dims)), timed(spark.read.parquet(f"{folder}/binary"))
    return spark.createDataFrame([(text, binary)], "text_s double, binary_s double")


def write_rows(df: DataFrame, path: str, kind: str = "parquet", by: list[str] | None = None) -> None:
    w = df.write.mode("overwrite").format(kind)
    (w.partitionBy(*by) if by else w).save(path)
