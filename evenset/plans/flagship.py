"""Tiles, vectors, tree, balanced subset, stratified plan, audit: the whole method in one query."""

from __future__ import annotations

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from ..operators import allocate, batching
from .methods import built, paths_of


def flagship(spark: SparkSession, sf: str, batch: int = 16, iterations: int = 142) -> DataFrame:
    """Per top cluster: size in pool and subset, draws, least and most views of a tile."""
    t = built(spark, sf, "narrow")
    sub = allocate.curate(paths_of(t), ["c4", "c3", "c2", "c1"], fraction=0.10)
    audit = batching.audit_plan(batching.plan_stratified(sub, "c4", batch, iterations))
    pool = t.sizes(4).select(F.col("node").alias("cluster"), F.col("n").alias("pool_tiles"))
    return pool.join(t.sizes(4, sub).select(F.col("node").alias("cluster"), F.col("n").alias("subset_tiles")), "cluster").join(audit, "cluster", "left")
