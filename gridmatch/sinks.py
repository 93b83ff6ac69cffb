"""Results and tiles written in the formats others read."""

from __future__ import annotations

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from .search.core import HITS

FORMATS = ("parquet", "orc", "json", "csv")


def with_cells(hits: DataFrame, w: int) -> DataFrame:
    """Adds `cells`, the region as text: row:column of each cell of the query, of width `w`."""
    bits = F.filter(F.sequence(F.lit(0), F.lit(61)), lambda i: F.getbit(F.col("mask"), i) == 1)
    place = F.transform(bits, lambda i: F.concat_ws(":", F.floor(i / w).cast("string"), (i % w).cast("string")))
    return hits.withColumn("cells", F.array_join(place, " "))


def write_hits(hits: DataFrame, path: str, format: str = "parquet", mode: str = "error") -> None:
    """`format` is parquet, orc, json or csv (with a header); all columns are plain values."""
    if format not in FORMATS:
        raise ValueError(f"format is one of {FORMATS}")
    hits.write.format(format).mode(mode).options(**({"header": "true"} if format == "csv" else {})).save(path)


def read_hits(spark: SparkSession, path: str, format: str = "parquet", more: str = "") -> DataFrame:
    """Hits as written, with the further columns `more` (a schema string)."""
    schema = HITS + (", " + more if more else "")
    if format == "csv":
        # a header names the columns, in whatever order they were written
        df = spark.read.option("header", "true").csv(path)
        return df.select(*[F.col(x.split()[0]).cast(x.split()[1]) for x in schema.split(", ")])
    return spark.read.format(format).schema(schema).load(path)


def bucketed(tiles: DataFrame, name: str, path: str, buckets: int) -> DataFrame:
    """The tiles as table `name` at `path`, clustered by image: what groups or joins by image_id
    reads it without an exchange."""
    tiles.write.bucketBy(buckets, "image_id").sortBy("image_id", "r", "c").option("path", path).mode("overwrite").saveAsTable(name)
    return tiles.sparkSession.table(name)
