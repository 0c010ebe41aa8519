"""Mixing sources to target weights: capped water-filling, then seeded whole and fractional repetitions.

Sources in code-point order (null last) take the given weights in turn and share all words. A source's target stops at
``max_epochs`` times its size; what it can't take is shared again by weight among the others, until none is above. With
sources ordered by cap over weight this end point is the first row at which the level of those still open is not above
its own cap, so one pass over prefix sums gives it.

Within a source every document is repeated floor(target / size) times. What is left of the target goes to a pseudo-random
prefix of its documents, ordered by a seeded MD5 of id and text: a document is in if the middle of its words is. So a source
misses its target by half a document at most, and the whole decision is one cut value for each source.

Cuts are found from word counts of 4096 hash bins for each source, then from the one bin that holds the cut; so a source with
a third of all rows is spread over as many groups. Null texts have no words. Documents of no words follow the cut, too.
Rows with one id and one text share a hash and are taken or left together. An empty table gives an empty result.
"""

from __future__ import annotations

from pyspark.sql import Column, DataFrame, Window
from pyspark.sql import functions as F

from keyloom.llm.common import SPACE, written

WEIGHTS = (5, 2, 1)
MAX_EPOCHS = 3
SEED = "mix-1"
#: Up to so many sources their table is broadcast; a larger one is joined by shuffle.
BROADCAST_SOURCES = 10_000


def n_words(text: Column) -> Column:
    return F.coalesce(F.regexp_count(text, F.lit(rf"[^{SPACE}]+")), F.lit(0)).cast("long")


def order_hash(id_col: Column, text: Column, seed: str) -> Column:
    """Of the id and the text, so that rows which share an id (all those without one) don't go together."""
    own = F.md5(F.coalesce(text.cast("string"), F.lit("")).cast("binary"))
    return F.md5(F.concat(F.lit(f"{seed}:"), F.coalesce(id_col.cast("string"), F.lit("")), F.lit(":"), own).cast("binary"))


def targets(sizes: DataFrame, weights: tuple[int, ...] = WEIGHTS, max_epochs: float = MAX_EPOCHS) -> DataFrame:
    """(source, source_size) -> the same with target (words). One row per source; the table is as small as that."""
    everything = Window.partitionBy(F.lit(1))
    by_name = Window.partitionBy(F.lit(1)).orderBy(F.col("source").asc_nulls_last())
    turn = F.pmod(F.row_number().over(by_name) - 1, F.lit(len(weights)))
    rows = sizes.withColumn("w", F.element_at(F.array(*map(F.lit, weights)), (turn + 1).cast("int")).cast("long"))
    rows = rows.withColumn("cap", F.col("source_size") * F.lit(max_epochs))
    by_level = Window.partitionBy(F.lit(1)).orderBy(F.col("cap").cast("double") / F.col("w"), F.col("source").asc_nulls_last())
    before = by_level.rowsBetween(Window.unboundedPreceding, -1)
    still = F.sum("source_size").over(everything) - F.coalesce(F.sum("cap").over(before), F.lit(0))
    open_w = F.sum("w").over(everything) - F.coalesce(F.sum("w").over(before), F.lit(0))
    rows = rows.withColumn("level", still.cast("double") / open_w.cast("double")).withColumn("nth", F.row_number().over(by_level))
    holds = F.when(F.col("cap").cast("double") / F.col("w") >= F.col("level"), F.struct("nth", "level"))
    rows = rows.withColumn("end", F.min(holds).over(everything)["level"])
    cap = F.col("cap").cast("double")
    return rows.select("source", "source_size", F.coalesce(F.least(cap, F.col("end") * F.col("w")), cap).alias("target"))


def plan(sized: DataFrame, weights: tuple[int, ...] = WEIGHTS, max_epochs: float = MAX_EPOCHS) -> DataFrame:
    """(source, size, h) of all documents -> (source, source_size, target, whole, cut): documents with h <= cut come once more than ``whole`` times."""
    bins, _ = written(sized.groupBy("source", F.substring("h", 1, 3).alias("bin")).agg(F.sum("size").alias("bin_size")), "bins")
    sources = targets(bins.groupBy("source").agg(F.sum("bin_size").alias("source_size")), weights, max_epochs)
    whole = F.when(F.col("source_size") > 0, F.floor(F.col("target") / F.col("source_size"))).otherwise(0)
    sources = sources.withColumn("whole", whole.cast("long")).withColumn("rest", F.col("target") - F.col("whole") * F.col("source_size"))
    sources, _ = written(sources, "sources")

    ahead = Window.partitionBy("source").orderBy("bin").rowsBetween(Window.unboundedPreceding, -1)
    placed = bins.withColumn("ahead", F.coalesce(F.sum("bin_size").over(ahead), F.lit(0))).withColumnRenamed("source", "s")
    reached = placed.join(sources.where("rest > 0"), F.col("s").eqNullSafe(F.col("source"))).where("ahead <= rest")
    crossing = reached.groupBy("source").agg(F.max(F.struct("bin", "ahead", "rest")).alias("x")).select(F.col("source").alias("s"), "x.*")
    crossing, _ = written(crossing, "crossing")

    near = sized.join(_small(crossing), F.col("s").eqNullSafe(F.col("source")) & F.col("h").startswith(F.col("bin"))).select("source", "size", "h", "ahead", "rest", "bin")
    within = Window.partitionBy("source", "bin").orderBy("h", "size").rowsBetween(Window.unboundedPreceding, -1)
    in_words = F.col("ahead") + F.coalesce(F.sum("size").over(within), F.lit(0))
    inside = near.withColumn("middle", 2 * in_words + F.col("size")).where(F.col("middle") <= 2 * F.col("rest"))
    last = inside.groupBy(F.col("source").alias("i")).agg(F.max("h").alias("last"))
    cuts = crossing.join(last, F.col("s").eqNullSafe(F.col("i")), "left").select("s", F.coalesce("last", "bin").alias("cut"))
    done = sources.join(cuts, F.col("source").eqNullSafe(F.col("s")), "left")
    return written(done.select("source", "source_size", "target", "whole", F.coalesce("cut", F.lit("")).alias("cut")), "mix")[0]


def _small(sources: DataFrame) -> DataFrame:
    return F.broadcast(sources) if sources.count() <= BROADCAST_SOURCES else sources


def copies() -> Column:
    return F.col("whole") + F.when(F.col("h") <= F.col("cut"), 1).otherwise(0)


def taken(docs: DataFrame, id_col: str = "doc_id", text_col: str = "text", source_col: str = "source", weights: tuple[int, ...] = WEIGHTS, max_epochs: float = MAX_EPOCHS, seed: str = SEED) -> DataFrame:
    """The rows of query op5: doc_id, size, source_size, target, taken; one row per document."""
    sized, _ = written(docs.select(F.col(id_col).alias("doc_id"), n_words(F.col(text_col)).alias("size"), F.col(source_col).alias("source"), order_hash(F.col(id_col), F.col(text_col), seed).alias("h")), "sized")
    sources = plan(sized, weights, max_epochs).withColumnRenamed("source", "s")
    mixed = sized.join(_small(sources), F.col("source").eqNullSafe(F.col("s")))
    return mixed.select("doc_id", "size", "source_size", "target", (F.col("size") * copies()).alias("taken"))


def mix(docs: DataFrame, id_col: str = "doc_id", text_col: str = "text", source_col: str = "source", weights: tuple[int, ...] = WEIGHTS, max_epochs: float = MAX_EPOCHS, seed: str = SEED) -> DataFrame:
    """The mix itself: the rows of ``docs``, each as many times as it is taken, all columns."""
    own = docs.select(F.col(source_col).alias("source"), n_words(F.col(text_col)).alias("size"), order_hash(F.col(id_col), F.col(text_col), seed).alias("h"), F.struct(*[F.col(f"`{c}`") for c in docs.columns]).alias("row"))
    sized, _ = written(own.select("source", "size", "h"), "sized")
    sources = plan(sized, weights, max_epochs).select(F.col("source").alias("s"), "whole", "cut")
    rows = own.join(_small(sources), F.col("source").eqNullSafe(F.col("s"))).select("row", copies().alias("times")).where("times > 0")
    return rows.select("row", F.explode(F.expr("sequence(1L, times)")).alias("nth")).select("row.*")



ORACLE = r"""
WITH sized AS (
  SELECT doc_id, source, CAST(coalesce(len(regexp_extract_all(text, '[^\x20\x09-\x0D]+')), 0) AS BIGINT) AS size,
         md5('mix-1:' || coalesce(CAST(doc_id AS VARCHAR), '') || ':' || md5(coalesce(text, ''))) AS h
  FROM documents),
per_source AS (SELECT source, CAST(sum(size) AS BIGINT) AS source_size FROM sized GROUP BY source),
weighed AS (
  SELECT *, source_size * 3 AS cap,
         CASE (row_number() OVER (ORDER BY source NULLS LAST) - 1) % 3 WHEN 0 THEN 5 WHEN 1 THEN 2 ELSE 1 END AS w
  FROM per_source),
levels AS (
  SELECT *, CAST(cap AS DOUBLE) / w AS own_level,
         CAST((SELECT sum(source_size) FROM weighed) - coalesce(sum(cap) OVER before, 0) AS DOUBLE)
           / CAST((SELECT sum(w) FROM weighed) - coalesce(sum(w) OVER before, 0) AS DOUBLE) AS level
  FROM weighed
  WINDOW before AS (ORDER BY CAST(cap AS DOUBLE) / w, source NULLS LAST ROWS BETWEEN UNBOUNDED PRECEDING AND 1 PRECEDING)),
filled AS (
  SELECT source, source_size, least(CAST(cap AS DOUBLE),
         (SELECT arg_min(level, own_level) FROM levels WHERE own_level >= level) * w) AS target
  FROM levels),
parts AS (
  SELECT *, CASE WHEN source_size > 0 THEN CAST(floor(target / source_size) AS BIGINT) ELSE 0 END AS whole FROM filled),
ordered AS (
  SELECT s.*, p.source_size, p.target, p.whole, p.target - p.whole * p.source_size AS rest,
         coalesce(sum(size) OVER (PARTITION BY s.source ORDER BY h, size ROWS BETWEEN UNBOUNDED PRECEDING AND 1 PRECEDING), 0) AS ahead
  FROM sized s JOIN parts p ON s.source IS NOT DISTINCT FROM p.source),
cuts AS (SELECT source, max(h) AS cut FROM ordered WHERE rest > 0 AND 2 * ahead + size <= 2 * rest GROUP BY source)
SELECT o.doc_id, o.size, o.source_size, o.target,
       o.size * (o.whole + CASE WHEN o.h <= c.cut THEN 1 ELSE 0 END) AS taken
FROM ordered o LEFT JOIN cuts c ON o.source IS NOT DISTINCT FROM c.source
"""
