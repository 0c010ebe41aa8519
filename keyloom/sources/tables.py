"""Readers of tables and of key-value files, and links out of pages."""

from __future__ import annotations

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F


def table(spark: SparkSession, sf_dir: str, name: str) -> DataFrame:
    return spark.read.parquet(f"{sf_dir}/{name}.parquet")


def read_pairs(spark: SparkSession, path: str, fmt: str, schema: str) -> DataFrame:
    """Key-value files: parquet, orc, csv (with a header), json, or text with tabs. The schema is given, never inferred."""
    if fmt == "text":
        names = [c.strip().split()[0] for c in schema.split(",")]
        parts = F.split("value", "\t")
        rows = spark.read.text(path).select(*[F.get(parts, i).alias(c) for i, c in enumerate(names)])
        kinds = [c.strip().split(None, 1)[1] for c in schema.split(",")]
        return rows.select(*[F.col(c).cast(k) for c, k in zip(names, kinds)])
    if fmt not in ("parquet", "orc", "csv", "json"):
        raise ValueError(fmt)
    reader = spark.read.schema(schema)
    return reader.option("header", True).csv(path) if fmt == "csv" else getattr(reader, fmt)(path)


def write_pairs(df: DataFrame, path: str, fmt: str = "parquet") -> None:
    writer = df.write.mode("overwrite")
    writer.option("header", True).csv(path) if fmt == "csv" else getattr(writer, fmt)(path)


def links(pages: DataFrame) -> DataFrame:
    """(page_id, target), distinct: where the anchors of each page point; a path is resolved against the page's scheme and authority."""
    host = F.regexp_extract("url", r"^([a-z]+://[^/]+)", 1)
    href = F.explode(F.expr(r"regexp_extract_all(html, '<a href=\"([^\"]*)\"', 1)"))
    rows = pages.select("page_id", host.alias("host"), href.alias("href"))
    return rows.select("page_id", F.when(F.col("href").startswith("/"), F.concat("host", "href")).otherwise(F.col("href")).alias("target")).distinct()


def raw_links(pages: DataFrame) -> DataFrame:
    """(page_id, path), distinct: the anchors as written."""
    return pages.select("page_id", F.explode(F.expr(r"regexp_extract_all(html, '<a href=\"([^\"]*)\"', 1)")).alias("path")).distinct()
