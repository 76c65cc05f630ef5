"""Batch plans: shuffled epochs and stratified batches with least-seen-first service.

Stratified plans need no counters: surplus slot e goes to cluster e mod k, so the draws of cluster o before
batch t are t*q + floor((t*r - o + k - 1) / k) with q = B div k, r = B mod k; draw j of a cluster of size s
is place j mod s of its permutation number j div s.
"""

from __future__ import annotations

import numpy as np
import pandas as pd
from pyspark.sql import DataFrame, Window
from pyspark.sql import functions as F

from ..functions.linalg import priority
from ..sources.tables import staged


def _ranges(df: DataFrame, order: list, parts: int | None) -> tuple[DataFrame, list[str]]:
    """Rows in range partitions, written once: range bounds come from a sample, so two runs of the same
    exchange need not agree and partition numbers must be fixed before they are counted."""
    parts = parts or int(df.sparkSession.conf.get("spark.sql.shuffle.partitions"))
    cols = [f"__o{i}" for i in range(len(order))]
    keyed = df.withColumns(dict(zip(cols, order))).repartitionByRange(parts, *cols).sortWithinPartitions(*cols).drop(*cols)
    return staged(keyed.withColumn("__p", F.spark_partition_id()).withColumn("__m", F.monotonically_increasing_id())), cols


def global_ordinal(df: DataFrame, order: list, name: str = "ordinal", parts: int | None = None) -> DataFrame:
    """Dense numbers in a global order without one task for all rows: range partitions and their offsets."""
    keyed, cols = _ranges(df, order, parts)
    first = keyed.groupBy("__p").agg(F.count("*").alias("__n"), F.min("__m").alias("__first"))
    starts = first.withColumn("__start", F.coalesce(F.sum("__n").over(Window.orderBy("__p").rowsBetween(Window.unboundedPreceding, -1)), F.lit(0)))
    out = keyed.join(F.broadcast(starts), "__p")  # one row per partition
    return out.withColumn(name, F.col("__start") + F.col("__m") - F.col("__first")).drop("__p", "__m", "__n", "__first", "__start", *cols)


def sum_before(df: DataFrame, order: list, value: str | dict[str, str], name: str = "before", parts: int | None = None) -> DataFrame:
    """Sum of `value` over all rows earlier in a global order (0 for the first), by range partitions and offsets.
    value may name several columns at once, as {column: name of its sum}."""
    values = {value: name} if isinstance(value, str) else value
    keyed, cols = _ranges(df, order, parts)
    back = Window.unboundedPreceding, -1
    sums = keyed.groupBy("__p").agg(*[F.sum(v).alias(f"__s_{n}") for v, n in values.items()])
    over = Window.orderBy("__p").rowsBetween(*back)
    starts = sums.select("__p", *[F.coalesce(F.sum(f"__s_{n}").over(over), F.lit(0)).alias(f"__start_{n}") for n in values.values()])
    inside = Window.partitionBy("__p").orderBy("__m").rowsBetween(*back)
    out = keyed.withColumns({f"__in_{n}": F.coalesce(F.sum(v).over(inside), F.lit(0)) for v, n in values.items()})
    out = out.join(F.broadcast(starts), "__p")
    out = out.withColumns({n: F.col(f"__start_{n}") + F.col(f"__in_{n}") for n in values.values()})
    return out.drop("__p", "__m", *cols, *[f"__{x}_{n}" for n in values.values() for x in ("in", "start")])


def plan_shuffled(subset: DataFrame, batch: int, iterations: int, seed: int = 17, mode: str = "epoch") -> DataFrame:
    """iteration, slot, point_id. epoch: fresh permutation per pass, cut into batches; replace: independent draws."""
    n = subset.count()
    spark = subset.sparkSession
    need = batch * iterations
    if mode == "replace":
        held = global_ordinal(subset.select("point_id"), [F.col("point_id")])
        draw = F.conv(F.substring(priority(seed, F.col("id")), 1, 15), 16, 10).cast("long")
        draws = spark.range(need).withColumn("ordinal", F.pmod(draw, F.lit(max(n, 1)).cast("long")))
        return draws.join(held, "ordinal").select((F.expr(f"id div {batch}")).alias("iteration"), (F.col("id") % batch).cast("int").alias("slot"), "point_id")
    passes = -(-need // max(n, 1))
    rows = subset.select("point_id").withColumn("epoch", F.explode(F.sequence(F.lit(0), F.lit(passes - 1))))
    key = F.md5(F.concat(F.lit(f"{seed}:"), F.col("epoch"), F.lit(":"), F.col("point_id")).cast("binary"))
    order = global_ordinal(rows, [F.col("epoch"), key, F.col("point_id")]).where(F.col("ordinal") < need)
    return order.select(
        F.expr(f"ordinal div {batch}").alias("iteration"), (F.col("ordinal") % batch).cast("int").alias("slot"), "point_id"
    )


def plan_stratified(subset: DataFrame, cluster_col: str, batch: int, iterations: int, seed: int = 17, strict: bool = False) -> DataFrame:
    """iteration, slot, cluster, point_id, seen_before: as many tiles of every cluster in each batch as can be,
    least-seen first. strict: no tile twice in a batch, by swaps where two passes of a cluster meet."""
    spark = subset.sparkSession
    turn = Window.orderBy("cluster")
    sizes = subset.groupBy(F.col(cluster_col).alias("cluster")).agg(F.count("*").alias("s"))
    sizes = sizes.withColumn("o", F.row_number().over(turn) - 1).withColumn("k", F.count("*").over(Window.partitionBy()))
    q, r = F.expr(f"{batch} div k"), F.expr(f"{batch} % k")

    def before(t):
        return t * q + F.floor((t * r - F.col("o") + F.col("k") - 1) / F.col("k"))

    t = F.col("iteration")
    grid = spark.range(iterations).withColumnRenamed("id", "iteration").crossJoin(F.broadcast(sizes))  # one row per cluster
    grid = grid.withColumn("from", before(t).cast("long")).withColumn("to", before(t + 1).cast("long")).where("to > from")
    draws = grid.withColumn("j", F.explode(F.sequence("from", F.col("to") - 1)))
    draws = draws.withColumn("pass", F.expr("j div s")).withColumn("place", F.expr("j % s"))
    last = sizes.withColumn("passes", F.expr(f"cast(({before_sql(iterations, batch)} + s - 1) div s as int)"))
    perms = subset.select("point_id", F.col(cluster_col).alias("cluster")).join(F.broadcast(last.select("cluster", "passes")), "cluster")
    perms = perms.where("passes > 0").withColumn("pass", F.explode(F.sequence(F.lit(0), F.col("passes") - 1)))
    key = F.md5(F.concat(F.lit(f"{seed}:"), F.col("pass"), F.lit(":"), F.col("point_id")).cast("binary"))
    perms = perms.withColumn("place", F.row_number().over(Window.partitionBy("cluster", "pass").orderBy(key, "point_id")) - 1)
    plan = draws.join(perms.withColumn("pass", F.col("pass").cast("long")), ["cluster", "pass", "place"])
    if strict:
        # repeats arise only in the batch where a pass ends and the next begins, so only draws near the ends of passes
        # are looked at: three batches' worth a pass
        per = F.expr(f"{batch} div k + 1")
        edge = (F.col("place") < 2 * per) | (F.col("place") >= F.col("s") - per)
        cols = ("iteration", F.col("cluster").cast("string").alias("cluster"), "j", "pass", "point_id")
        plan = staged(plan.withColumn("edge", edge))
        swapped = plan.where("edge").select(*cols).groupBy("cluster").applyInPandas(_no_repeats, "iteration long, cluster string, j long, pass long, point_id long")
        plan = swapped.unionByName(plan.where("not edge").select(*cols))
    slot = F.row_number().over(Window.partitionBy("iteration").orderBy("cluster", "j")) - 1
    return plan.select("iteration", slot.cast("int").alias("slot"), "cluster", "point_id", F.col("pass").alias("seen_before"))


def plan_hierarchical(subset: DataFrame, cluster_col: str, child_col: str, batch: int, iterations: int, seed: int = 17) -> DataFrame:
    """iteration, slot, cluster, child, point_id, seen_before: batches even over clusters whose draws go round the
    children of the cluster in turn, least-seen tiles of each child first. Draw j of a cluster with m children is draw
    j div m of its child j mod m."""
    spark = subset.sparkSession
    rows = subset.select("point_id", F.col(cluster_col).alias("cluster"), F.col(child_col).alias("child"))
    nodes = rows.groupBy("cluster", "child").agg(F.count("*").alias("s"))
    nodes = nodes.withColumn("o2", F.row_number().over(Window.partitionBy("cluster").orderBy("child")) - 1)
    tops = nodes.groupBy("cluster").agg(F.count("*").alias("m"))
    tops = tops.withColumn("o", F.row_number().over(Window.orderBy("cluster")) - 1).withColumn("k", F.count("*").over(Window.partitionBy()))
    t, q, r = F.col("iteration"), F.expr(f"{batch} div k"), F.expr(f"{batch} % k")
    before = lambda t: (t * q + F.floor((t * r - F.col("o") + F.col("k") - 1) / F.col("k"))).cast("long")
    grid = spark.range(iterations).withColumnRenamed("id", "iteration").crossJoin(F.broadcast(tops))  # one row per cluster
    grid = grid.withColumn("from", before(t)).withColumn("to", before(t + 1)).where("to > from")
    draws = grid.withColumn("j", F.explode(F.sequence("from", F.col("to") - 1)))
    draws = draws.withColumn("o2", F.expr("cast(j % m as int)")).join(nodes, ["cluster", "o2"])
    draws = draws.withColumn("pass", F.expr("(j div m) div s")).withColumn("place", F.expr("(j div m) % s"))
    most = tops.join(nodes, "cluster").select("cluster", "child", F.expr(f"cast(({before_sql(iterations, batch)} div m + s) div s as int)").alias("passes"))
    perms = rows.join(most, ["cluster", "child"]).withColumn("pass", F.explode(F.sequence(F.lit(0).cast("long"), F.col("passes").cast("long"))))
    key = F.md5(F.concat(F.lit(f"{seed}:"), F.col("pass"), F.lit(":"), F.col("point_id")).cast("binary"))
    turn = Window.partitionBy("cluster", "child", "pass").orderBy(key, "point_id")
    perms = perms.withColumn("place", (F.row_number().over(turn) - 1).cast("long"))
    plan = draws.join(perms.select("cluster", "child", "pass", "place", "point_id"), ["cluster", "child", "pass", "place"])
    slot = F.row_number().over(Window.partitionBy("iteration").orderBy("cluster", "j")) - 1
    return plan.select("iteration", slot.cast("int").alias("slot"), "cluster", "child", "point_id", F.col("pass").alias("seen_before"))


def before_sql(t: int, batch: int) -> str:
    return f"({t} * ({batch} div k) + cast(floor(({t} * ({batch} % k) - o + k - 1) / k) as bigint))"


def _no_repeats(pdf: pd.DataFrame) -> pd.DataFrame:
    """Swap within a pass so that no batch holds a tile twice where two passes meet."""
    pdf = pdf.sort_values("j", ignore_index=True)
    ids, it, run = pdf["point_id"].to_numpy().copy(), pdf["iteration"].to_numpy(), pdf["pass"].to_numpy()
    for i in range(len(ids)):
        lo = np.searchsorted(it, it[i])
        if ids[i] in ids[lo:i]:
            for j in range(i + 1, np.searchsorted(run, run[i], "right")):
                if ids[j] not in ids[lo:i] and it[j] != it[i]:
                    ids[i], ids[j] = ids[j], ids[i]
                    break
    out = pdf.assign(point_id=ids, cluster=pdf["cluster"].astype(str))
    return out[["iteration", "cluster", "j", "pass", "point_id"]]


def audit_plan(plan: DataFrame) -> DataFrame:
    """Per cluster: draws, least and most per batch, least and most views of a tile."""
    per_batch = plan.groupBy("cluster", "iteration").agg(F.count("*").alias("n")).groupBy("cluster").agg(
        F.sum("n").alias("draws"), F.min("n").alias("least_per_batch"), F.max("n").alias("most_per_batch")
    )
    views = plan.groupBy("cluster", "point_id").agg(F.count("*").alias("v")).groupBy("cluster").agg(
        F.count("*").alias("tiles_seen"), F.min("v").alias("least_views"), F.max("v").alias("most_views")
    )
    return per_batch.join(views, "cluster")


def batch_tv(plan: DataFrame, k: int) -> DataFrame:
    """Total variation from uniform of every batch over k clusters, summed up as mean and max."""
    n = plan.groupBy("iteration", "cluster").agg(F.count("*").alias("n"))
    size = Window.partitionBy("iteration")
    p = n.withColumn("p", F.col("n") / F.sum("n").over(size))
    tv = p.groupBy("iteration").agg(((F.sum(F.abs(F.col("p") - 1 / F.lit(k))) + (k - F.count("*")) / k) / 2).alias("tv"))
    return tv.agg(F.avg("tv").alias("mean_tv"), F.max("tv").alias("max_tv"))


def plan_cost(plan: DataFrame, subset: DataFrame, pool: DataFrame) -> DataFrame:
    """Tiles fed, and passes over subset and pool."""
    one = lambda df, c: df.agg(F.count("*").alias(c))
    s = one(plan, "fed").crossJoin(one(subset, "sub")).crossJoin(one(pool, "all"))
    return s.select("fed", (F.col("fed") / F.col("sub")).alias("subset_passes"), (F.col("fed") / F.col("all")).alias("pool_passes"))


def write_plan(plan: DataFrame, path: str, parts: int = 8, records: int = 1_000_000) -> None:
    """Files sorted by iteration and slot, for an external trainer."""
    plan.repartitionByRange(parts, "iteration").sortWithinPartitions("iteration", "slot").write.option(
        "maxRecordsPerFile", records
    ).parquet(path)
