"""Small distributed helpers of the training-data operators; storage is the library's."""

from __future__ import annotations

from collections.abc import Callable

from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from floorwalk.sources.scratch import discard, materialize, shared_folder

__all__ = ["connected_components", "content_keys", "discard", "guarded", "materialize", "materialize_texts", "shared_folder"]

DOCUMENT = ("doc_id", "text", "lang", "source", "n_chars")


BATCH_ROWS = "spark.sql.execution.arrow.maxRecordsPerBatch"


def materialize_texts(frame: DataFrame, rows: int = 512) -> DataFrame:
    """materialize() for plans that hand whole texts to Python: few rows a batch while it is written, so that neither side
    holds ten thousand texts at once."""
    conf = frame.sparkSession.conf
    before = conf.get(BATCH_ROWS)
    conf.set(BATCH_ROWS, str(rows if int(before) <= 0 else min(rows, int(before))))
    try:
        return materialize(frame)
    finally:
        conf.set(BATCH_ROWS, before)


def content_keys(*columns: str) -> list[F.Column]:
    """Two 64-bit hashes (k1, k2) of the named columns, nulls told apart: rows that agree in them agree in the columns."""
    parts = [part for c in columns for part in (F.col(c).isNull(), F.col(c))]
    return [F.xxhash64(F.lit(1), *parts).alias("k1"), F.xxhash64(F.lit(2), *reversed(parts)).alias("k2")]


def guarded(docs: DataFrame, work: Callable[[DataFrame], DataFrame], own: tuple[str, ...] = DOCUMENT) -> DataFrame:
    """work(docs) with its columns in order, under names that no operator uses while it runs: extra columns of any name pass."""
    names = docs.columns
    inner = [c if c in own else f"extra_{i}" for i, c in enumerate(names)]
    return work(docs.toDF(*inner)).select(*inner).toDF(*names)


def connected_components(edges: DataFrame, max_rounds: int = 60) -> DataFrame:
    """Components of an undirected graph given as (a, b): one row (node, root) per node of an edge, root the least id.

    Alternates two star contractions, each a grouped minimum and a join, until nothing changes: a logarithmic number
    of rounds in practice, no node's neighbours are ever gathered in one place, and each round is written to the shared
    folder. An empty edge table gives an empty result.
    """
    pairs = edges.where("a <> b").select(F.greatest("a", "b").alias("u"), F.least("a", "b").alias("v")).distinct()
    pairs = materialize(pairs)
    before = None
    for _ in range(max_rounds):
        both = pairs.union(pairs.select("v", "u"))
        low = both.groupBy("u").agg(F.min("v").alias("m")).select("u", F.least("u", "m").alias("m"))
        large = both.join(low, "u").where("v > u").select(F.col("v").alias("u"), F.col("m").alias("v")).where("u <> v").distinct()
        low = large.groupBy("u").agg(F.min("v").alias("m"))
        joined = large.join(low, "u")
        small = joined.select(F.col("v").alias("u"), F.col("m").alias("v")).union(joined.select("u", F.col("m").alias("v")))
        last, pairs = pairs, materialize(small.where("u <> v").distinct())
        discard(last)
        state = pairs.agg(F.count("*"), F.sum(F.xxhash64("u", "v").cast("decimal(38,0)"))).first()
        if state == before:
            break
        before = state
    else:
        raise RuntimeError(f"components did not settle in {max_rounds} rounds")
    nodes = pairs.select(F.col("u").alias("node"), F.col("v").alias("root"))
    return nodes.union(pairs.select(F.col("v").alias("node"), F.col("v").alias("root")).distinct())
