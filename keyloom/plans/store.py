"""Filters as directories: tables by group of shards, then a manifest that makes them complete."""

from __future__ import annotations

import json
from dataclasses import asdict

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from keyloom.operators.lookup import Filter
from keyloom.plans.params import Spec

VERSION = 2


def save(filter: Filter, path: str, groups: int = 64) -> None:
    """Writes shards in ``groups`` partitions, so that a point lookup reads one, and the manifest last."""
    filter.tables.withColumn("shard_group", F.col("shard") % groups).write.mode("overwrite").partitionBy("shard_group").parquet(f"{path}/tables")
    spark = filter.tables.sparkSession
    row = (VERSION, json.dumps(asdict(filter.spec)), filter.key_types, filter.n, filter.version, filter.batch, groups)
    spark.createDataFrame([row], "format int, spec string, key_types array<string>, n long, version int, batch long, groups int").write.mode("overwrite").parquet(f"{path}/manifest")


def load(spark: SparkSession, path: str) -> Filter:
    head = spark.read.parquet(f"{path}/manifest").first()
    if head["format"] != VERSION:
        raise ValueError(f"format {head['format']}")
    return Filter(Spec(**json.loads(head["spec"])), list(head["key_types"]), spark.read.parquet(f"{path}/tables").drop("shard_group"), head["n"], head["version"], head["batch"])


def checksum(tables: DataFrame) -> int:
    """One number for all arrays, whatever the order of rows."""
    cell = F.xxhash64("shard", "n_slots", "seed", "g", "h", "b")
    return tables.agg(F.bit_xor(cell)).first()[0]


def register(filter: Filter, name: str) -> None:
    """The filter's tables as a temporary view."""
    filter.tables.createOrReplaceTempView(name)
