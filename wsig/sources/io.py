"""Reading bags and events, writing signatures."""

from __future__ import annotations

from pyspark.sql import DataFrame, SparkSession

from wsig.schema import BAG

FORMATS = ("parquet", "orc", "json", "csv")


def load_bags(spark: SparkSession, path: str, fmt: str = "parquet") -> DataFrame:
    """Bags from files of any supported format, by the fixed schema rather than by inference."""
    if fmt not in FORMATS:
        raise ValueError(f"format is one of {FORMATS}")
    reader = spark.read.schema(BAG)
    return reader.option("header", True).csv(path) if fmt == "csv" else reader.format(fmt).load(path)


def save_bags(bags: DataFrame, path: str, fmt: str = "parquet") -> None:
    writer = bags.select("bag_id", "elem", "weight").write
    (writer.option("header", True) if fmt == "csv" else writer).format(fmt).save(path)


def bags_from_rows(spark: SparkSession, rows: list[tuple]) -> DataFrame:
    return spark.createDataFrame(rows, BAG)


def write_signatures(sigs: DataFrame, path: str, spec: str) -> None:
    """Signatures under a folder for their spec (salt, draws, ladder, size), so that only comparable ones are read together."""
    from pyspark.sql import functions as F

    sigs.withColumn("spec", F.lit(spec)).write.mode("append").partitionBy("spec").parquet(path)


def read_signatures(spark: SparkSession, path: str, spec: str) -> DataFrame:
    return spark.read.parquet(path).where(f"spec = '{spec}'").drop("spec")


def save_bucketed(sigs: DataFrame, table: str, buckets: int, key: str = "bag_id") -> None:
    """A table bucketed and sorted by key, so that later joins on it need no shuffle."""
    sigs.write.mode("overwrite").bucketBy(buckets, key).sortBy(key).saveAsTable(table)


def stream_table(spark: SparkSession, sf_dir: str, name: str, max_files: int = 1) -> DataFrame:
    """A table's files as a stream, in its own schema."""
    path = f"{sf_dir}/{name}.parquet"
    schema = spark.read.parquet(path).schema
    jvm = spark.sparkContext._jvm
    at = jvm.org.apache.hadoop.fs.Path(path)
    folder = at.getFileSystem(spark.sparkContext._jsc.hadoopConfiguration()).getFileStatus(at).isDirectory()
    reader = spark.readStream.schema(schema).option("maxFilesPerTrigger", max_files)
    return reader.parquet(path) if folder else reader.option("pathGlobFilter", f"{name}.parquet").parquet(sf_dir)
