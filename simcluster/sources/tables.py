"""Reading tables and geometry files with explicit schemas, writing results."""

from __future__ import annotations

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from ..functions import geom as G
from ..functions import text as X

SCHEMAS = {
    "orders": "o_orderkey long, o_custkey long, o_totalprice double, o_orderdate timestamp",
    "customer": "c_custkey long, c_nationkey int, c_mktsegment string",
    "part": "p_partkey long, p_size int, p_brand string, p_type string",
    "lineitem": "l_orderkey long, l_partkey long, l_suppkey long, l_linenumber int, l_quantity double, l_linestatus string",
    "events": "event_id long, user_id long, ts timestamp, event_type string, value double, props string",
    "embeddings": "vec_id long, embedding array<float>, label int",
}


def load_table(spark: SparkSession, sf_dir: str, name: str) -> DataFrame:
    """A given table, with the columns that the lifts need where these are listed."""
    path = f"{sf_dir}/{name}.parquet"
    return spark.read.schema(SCHEMAS[name]).parquet(path) if name in SCHEMAS else spark.read.parquet(path)


def read_wkt_csv(spark: SparkSession, path: str, id_col: str = "id", wkt_col: str = "wkt", header: bool = True) -> DataFrame:
    """id and geom from CSV files with a column of well-known text."""
    raw = spark.read.schema(f"{id_col} long, {wkt_col} string").option("header", header).option("escape", '"').csv(path)
    return raw.select(F.col(id_col).alias("id"), X.from_wkt(F.col(wkt_col)).alias("geom"))


def read_geojson(spark: SparkSession, path: str, id_path: str = "$.properties.id") -> DataFrame:
    """id and geom from files with one GeoJSON feature per line."""
    raw = spark.read.text(path)
    return raw.select(F.get_json_object("value", id_path).cast("long").alias("id"), X.from_geojson(F.get_json_object("value", "$.geometry")).alias("geom")).filter("geom is not null")


def write_wkt_csv(df: DataFrame, path: str) -> None:
    df.select("id", X.to_wkt(F.col("geom")).alias("wkt")).write.option("header", True).option("escape", '"').csv(path)


def write_geojson(df: DataFrame, path: str) -> None:
    line = F.concat(F.lit('{"type":"Feature","properties":{"id":'), F.col("id").cast("string"), F.lit('},"geometry":'), X.to_geojson(F.col("geom")), F.lit("}"))
    df.select(line.alias("value")).write.text(path)


def write_results(df: DataFrame, path: str, partition_by: tuple[str, ...] = (), mode: str = "errorifexists") -> None:
    """A result as Parquet files, in folders by the given columns."""
    writer = df.write.mode(mode)
    (writer.partitionBy(*partition_by) if partition_by else writer).parquet(path)


def write_bucketed(df: DataFrame, table: str, buckets: int, by: str, mode: str = "overwrite") -> None:
    """A catalog table bucketed and sorted by a key: joins on the key need no shuffle."""
    df.write.mode(mode).bucketBy(buckets, by).sortBy(by).saveAsTable(table)


def within_box(df: DataFrame, x1: float, y1: float, x2: float, y2: float, box: str = "mbr") -> DataFrame:
    """Rows whose box meets a region; on stored boxes the comparisons reach the Parquet statistics."""
    b = F.col(box)
    return df.filter((b["x1"] <= x2) & (b["x2"] >= x1) & (b["y1"] <= y2) & (b["y2"] >= y1))


def with_box(df: DataFrame) -> DataFrame:
    return df.withColumn("mbr", G.mbr(F.col("geom")))
