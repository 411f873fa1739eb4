"""The given tables, edge lists from files, and the sinks of results."""

from __future__ import annotations

import atexit
import shutil
import tempfile
import uuid

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

EDGE_SCHEMA = "src long, dst long"


def load(spark: SparkSession, sf_dir: str, name: str) -> DataFrame:
    return spark.read.parquet(f"{sf_dir}/{name}.parquet")


def shared_folder(spark: SparkSession, name: str) -> str:
    """A new folder that driver and executors share: below spark.checkpoint.dir; where that is unset, a temporary one in one process, and an error on a cluster."""
    named = spark.conf.get("spark.checkpoint.dir", None) or spark.sparkContext.getConf().get("spark.checkpoint.dir")
    if not named:
        if spark.sparkContext.master != "local" and not spark.sparkContext.master.startswith("local["):
            raise ValueError("spark.checkpoint.dir must name a folder that the driver and all executors share")
        named = tempfile.mkdtemp(prefix="motifscan-")
        atexit.register(shutil.rmtree, named, True)
    return f"{named.rstrip('/')}/{name}-{uuid.uuid4().hex}"


def kept(df: DataFrame, name: str) -> DataFrame:
    """df written once in the shared folder, for plans that read it more than once."""
    path = shared_folder(df.sparkSession, name)
    df.write.parquet(path)
    return df.sparkSession.read.schema(df.schema).parquet(path)


def read_edges(spark: SparkSession, path: str, format: str = "parquet", src: str = "src", dst: str = "dst", label: str | None = None, **options: str) -> DataFrame:
    """An edge list (src, dst[, label]) from Parquet, ORC, JSON, CSV or text (two numbers a line, split by white space), with the schema given, never inferred."""
    if format == "text":
        part = F.split(F.trim("value"), r"\s+")
        return spark.read.options(**options).text(path).where(~F.col("value").startswith("#") & (F.size(part) >= 2)).select(part[0].cast("long").alias("src"), part[1].cast("long").alias("dst"))
    schema = f"`{src}` long, `{dst}` long" + (f", `{label}` string" if label else "")
    df = spark.read.format(format).schema(schema).options(**options).load(path)
    return df.select(F.col(src).alias("src"), F.col(dst).alias("dst"), *([F.col(label).alias("label")] if label else []))


def page_links(pages: DataFrame) -> DataFrame:
    """Edges between the hosts that pages are on and link to, as strings (from_host, to_host)."""
    links = pages.select(F.regexp_extract("url", r"^[a-z]+://([^/]+)", 1).alias("from_host"), F.explode(F.regexp_extract_all("html", F.lit(r'href="([^"]+)"'), 1)).alias("href"))
    to = F.regexp_extract("href", r"^[a-z]+://([^/]+)", 1)
    return links.select("from_host", F.when(to == "", F.col("from_host")).otherwise(to).alias("to_host")).where("from_host <> to_host").distinct()


def number_nodes(pairs: DataFrame, a: str, b: str) -> tuple[DataFrame, DataFrame]:
    """(edges with long ids, dictionary (id, name)) of string edges. Ids are 64-bit hashes, and a collision stops the job."""
    names = pairs.select(F.col(a).alias("name")).union(pairs.select(b)).where("name is not null").distinct()
    dictionary = names.select(F.xxhash64("name").alias("id"), "name").groupBy("id").agg(F.min("name").alias("name"), F.max("name").alias("other"))
    checked = dictionary.select("id", F.when(F.col("name") == F.col("other"), F.col("name")).otherwise(F.raise_error(F.lit("two names share an id")).cast("string")).alias("name"))
    return pairs.select(F.xxhash64(a).alias("src"), F.xxhash64(b).alias("dst")), checked


def write_instances(df: DataFrame, path: str, partition_by: str | None = None, format: str = "parquet", mode: str = "errorifexists") -> None:
    writer = df.write.format(format).mode(mode)
    (writer.partitionBy(partition_by) if partition_by else writer).save(path)
