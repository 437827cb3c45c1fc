"""Readers and writers: pruned scans, fixed-width records, ordered files with a manifest, copies."""

from __future__ import annotations

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F
from pyspark.sql import types as T

from ..plans.extsort import PID, SortedFrame, estimated_bytes


def read_table(spark: SparkSession, folder: str, name: str) -> DataFrame:
    return spark.read.parquet(f"{folder}/{name}.parquet")


def read_records(spark: SparkSession, path: str, fmt: str, schema: str | T.StructType, **options) -> DataFrame:
    """CSV, JSON, ORC or Parquet by a given schema: no pass over the data to infer one."""
    return spark.read.format(fmt).schema(schema).options(**options).load(path)


def read_fixed(spark: SparkSession, path: str, widths: dict[str, int]) -> DataFrame:
    """Text lines cut into columns by width."""
    df, at = spark.read.text(path), 1
    columns = []
    for name, n in widths.items():
        columns.append(F.substring("value", at, n).alias(name))
        at += n
    return df.select(*columns)


def read_striped(spark: SparkSession, path: str, readers: int) -> DataFrame:
    """A Parquet scan cut into about `readers` equal byte ranges."""
    total = estimated_bytes(spark.read.parquet(path))
    name = "spark.sql.files.maxPartitionBytes"
    before = spark.conf.get(name)
    spark.conf.set(name, str(max(1, -(-total // max(1, readers)))))
    try:
        out = spark.read.parquet(path)
        out.rdd.getNumPartitions()  # fixes the splits under this setting
        return out
    finally:
        spark.conf.set(name, before)


def write_fixed(df: DataFrame, path: str, widths: dict[str, int], mode: str = "overwrite") -> None:
    df.select(F.concat(*[F.rpad(F.col(c).cast("string"), n, " ") for c, n in widths.items()]).alias("value")).write.mode(mode).text(path)


def write_sorted(sf: SortedFrame, path: str, *, fmt: str = "parquet", codec: str | None = None) -> DataFrame:
    """Writes slices in order with their places and returns the manifest, also kept beside the data.

    Rows carry rn, so readers never depend on file names or listing order.
    """
    writer = sf.with_rn("rn").sortWithinPartitions("rn").write.mode("overwrite").format(fmt)
    if codec:
        writer = writer.option("compression", codec)
    writer.save(f"{path}/data")
    manifest = read_manifest_of(sf.spark, path, fmt)
    manifest.write.mode("overwrite").parquet(f"{path}/manifest")
    return sf.spark.read.parquet(f"{path}/manifest")


def read_manifest_of(spark: SparkSession, path: str, fmt: str = "parquet") -> DataFrame:
    """(pid, rows, row_offset, path) of the files that a sorted write left, in order."""
    from pyspark.sql import Window

    data = spark.read.format(fmt).load(f"{path}/data")
    files = data.groupBy(F.input_file_name().alias("path")).agg(F.count("*").alias("rows"), F.min("rn").alias("first"))
    order = Window.orderBy("first")  # one row a file
    before = F.coalesce(F.sum("rows").over(order.rowsBetween(Window.unboundedPreceding, -1)), F.lit(0))
    return files.select((F.row_number().over(order) - 1).alias("pid"), "rows", before.alias("row_offset"), "path", "first")


def read_sorted(spark: SparkSession, path: str, fmt: str = "parquet", *, low: int | None = None, high: int | None = None) -> DataFrame:
    """The rows of a sorted write with rn; low..high reads only the files that hold those places."""
    if low is None and high is None:
        return spark.read.format(fmt).load(f"{path}/data")
    m = spark.read.parquet(f"{path}/manifest")
    low, high = low or 1, high if high is not None else 1 << 62
    names = [r[0] for r in m.filter((F.col("row_offset") < high) & (F.col("row_offset") + F.col("rows") >= low)).orderBy("pid").select("path").collect()]
    df = spark.read.format(fmt).load(names) if names else spark.read.format(fmt).load(f"{path}/data").limit(0)
    return df.filter(F.col("rn").between(low, high))


def write_sharded(sf: SortedFrame, path: str, fmt: str = "parquet") -> None:
    """A folder for each slice: readers prune by slice."""
    sf.df.withColumnRenamed(PID, "pid").write.mode("overwrite").format(fmt).partitionBy("pid").save(path)


def write_bucketed(df: DataFrame, table: str, key: str, f: int) -> None:
    """A bucketed, sorted table: joins and groups on the key need no exchange."""
    df.write.mode("overwrite").bucketBy(f, key).sortBy(key).format("parquet").saveAsTable(table)


def copy_baseline(df: DataFrame, path: str, fmt: str = "parquet", codec: str | None = None) -> None:
    """Read all, write all."""
    writer = df.write.mode("overwrite").format(fmt)
    (writer.option("compression", codec) if codec else writer).save(path)


def write_noop(df: DataFrame) -> None:
    df.write.format("noop").mode("overwrite").save()
