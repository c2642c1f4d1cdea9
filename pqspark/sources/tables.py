"""Codes, codebooks and graphs as stored tables: checked reads, whole replacements, lists as partitions, buckets, clustered order."""

from __future__ import annotations

import uuid

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F
from pyspark.sql import types as T

VECTORS = "vec_id long, embedding array<float>, label int"


def read(spark: SparkSession, path: str, schema: str = VECTORS, kind: str = "parquet") -> DataFrame:
    """A table with declared columns; a missing column or another type is an error, further columns are not read."""
    declared = T.StructType.fromDDL(schema)
    found = {f.name: f.dataType.simpleString() for f in spark.read.format(kind).load(path).schema}
    drift = [f"{f.name}: {found.get(f.name, 'missing')} instead of {f.dataType.simpleString()}" for f in declared if found.get(f.name) != f.dataType.simpleString()]
    if drift:
        raise ValueError(f"{path} has another schema: {'; '.join(drift)}")
    return spark.read.format(kind).schema(declared).load(path)


def write(df: DataFrame, path: str, kind: str = "parquet", by: tuple[str, ...] = ()) -> None:
    """Replace the table under path: written beside it and renamed at the end, so that no reader meets half a table.

    df may read the old table.  Between the two renames the path is absent for a moment.
    """
    spark = df.sparkSession
    trial, aside = f"{path}.{uuid.uuid4().hex}", f"{path}.{uuid.uuid4().hex}"
    df.write.format(kind).partitionBy(*by).save(trial)
    at = lambda p: spark._jvm.org.apache.hadoop.fs.Path(p)
    fs = at(path).getFileSystem(spark._jsc.hadoopConfiguration())
    old = fs.exists(at(path))
    if old and not fs.rename(at(path), at(aside)):
        raise OSError(f"can't move {path} aside")
    if not fs.rename(at(trial), at(path)):
        raise OSError(f"can't name {trial} {path}")
    if old:
        fs.delete(at(aside), True)


def write_lists(df: DataFrame, path: str, column: str = "list") -> None:
    """A folder for each list; rows are brought together by list, and a list too large for a task is split among several."""
    write(df.hint("rebalance", F.col(column)), path, by=(column,))


def scan_lists(spark: SparkSession, path: str, lists: list[int], column: str = "list") -> DataFrame:
    """Rows of some lists; folders of others are not opened."""
    return spark.read.parquet(path).filter(F.col(column).isin(lists))


def write_buckets(df: DataFrame, name: str, buckets: int, by: str = "vec_id") -> DataFrame:
    """A catalog table in buckets by id, each sorted, so that tables written alike join without a shuffle."""
    df.write.bucketBy(buckets, by).sortBy(by).mode("overwrite").saveAsTable(name)
    return df.sparkSession.table(name)


def sort_codes(df: DataFrame, column: str = "codes") -> DataFrame:
    """Rows in ranges of their codes; the id breaks ties, so that rows of one frequent code are dealt out as well."""
    return df.repartitionByRange(column, "vec_id").sortWithinPartitions(column, "vec_id")
