"""Reading tables and page collections, and writing regions."""

from __future__ import annotations

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from ..session import ship


def load(spark: SparkSession, sf_dir: str, name: str) -> DataFrame:
    ship(spark)
    return spark.read.parquet(f"{sf_dir}/{name}.parquet")


def read_crawl(spark: SparkSession, path: str, encoding: str = "UTF-8") -> DataFrame:
    """A folder of saved pages as (page_id, url, html); the id is a hash of the path."""
    raw = spark.read.format("binaryFile").option("recursiveFileLookup", "true").load(path)
    return raw.select(F.xxhash64("path").alias("page_id"), F.col("path").alias("url"), F.decode("content", encoding).alias("html"))


def read_pages(spark: SparkSession, path: str, fmt: str = "parquet") -> DataFrame:
    """Pages from Parquet, JSON lines or CSV with the columns page_id, url, html."""
    schema = "page_id long, url string, html string"
    reader = spark.read.schema(schema)
    if fmt == "csv":
        reader = reader.option("header", "true").option("multiLine", "true").option("escape", '"')
    return reader.format(fmt).load(path)


#: Regions in one bucket, about.
BUCKET_ROWS = 2_000_000


def write_regions(regions: DataFrame, table: str, buckets: int | None = None, mode: str = "overwrite") -> DataFrame:
    """Store regions bucketed by page, one file a bucket, so that rules need no shuffle; buckets follow the regions."""
    buckets = buckets or max(regions.sparkSession.sparkContext.defaultParallelism, regions.count() // BUCKET_ROWS)
    (
        regions.repartition(buckets, "page_id")
        .sortWithinPartitions("page_id", "ord")
        .write.mode(mode)
        .bucketBy(buckets, "page_id")
        .sortBy("page_id", "ord")
        .saveAsTable(table)
    )
    return regions.sparkSession.table(table)


def write_matches(matches: DataFrame, path: str, mode: str = "overwrite") -> None:
    matches.write.mode(mode).parquet(path)
