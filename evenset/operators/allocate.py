"""Budgets down a tree: one common cap per parent, its children's sizes, and the draw inside leaves.

A tree is a table of leaves with one column per level (top first) and a size. Only such node tables move;
points are touched once, in the draw.
"""

from __future__ import annotations

from pyspark.sql import DataFrame, Window
from pyspark.sql import functions as F

from ..functions.linalg import priority, sq_dist, uniform
from ..sources.tables import staged
from .batching import global_ordinal, sum_before
from .kmeans_table import least_priority


def fill_level_bisect(sizes: list[int], budget: int) -> int:
    """The cap n in 0..max(sizes) whose total of min(n, size) is nearest to budget; ties go to the lower cap."""
    total = lambda n: sum(min(n, s) for s in sizes)
    low, high = 0, max(sizes, default=0)
    while low < high:
        mid = (low + high) // 2
        if total(mid) < budget:
            low = mid + 1
        else:
            high = mid
    return low - 1 if low and abs(total(low - 1) - budget) <= abs(total(low) - budget) else low


def exhaust_budget(sizes: list[int]) -> list[int]:
    """Least budget whose nearest cap takes each child whole."""
    total = lambda n: sum(min(n, s) for s in sizes)
    return [(total(s - 1) + total(s)) // 2 + 1 if s else 0 for s in sizes]


def fill_levels(children: DataFrame, parent: list[str], child: str, size: str = "size", budget: str = "budget") -> DataFrame:
    """parent columns, cap, total, miss for all parents at once. With sizes in order, the total is linear
    between neighbouring sizes, so two integers per piece hold the best cap."""
    by = Window.partitionBy(*parent).orderBy(size, child)
    pieces = (
        children.select(*parent, child, size, budget)
        .withColumn("__k", F.count("*").over(Window.partitionBy(*parent)))
        .withColumn("__m", F.col("__k") - F.row_number().over(by) + 1)
        .withColumn("__before", F.coalesce(F.sum(size).over(by.rowsBetween(Window.unboundedPreceding, -1)), F.lit(0)))
        .withColumn("__low", F.coalesce(F.lag(size).over(by), F.lit(0)))
    )
    root = F.floor((F.col(budget) - F.col("__before")) / F.col("__m")).cast("long")
    tries = pieces.withColumn("__n", F.explode(F.array(root, root + 1))).withColumn(
        "__n", F.greatest(F.col("__low"), F.least(F.col("__n"), F.col(size))).cast("long")
    )
    total = (F.col("__before") + F.col("__m") * F.col("__n")).cast("long")
    scored = tries.withColumn("__total", total).withColumn("__miss", F.abs(F.col(budget) - F.col("__total")).cast("long"))
    best = scored.groupBy(*parent).agg(F.min(F.struct("__miss", "__n", "__total")).alias("__b"))
    return best.select(
        *parent, F.col("__b.__n").alias("cap"), F.col("__b.__total").alias("total"), F.col("__b.__miss").alias("miss")
    )


def allocate_level(
    children: DataFrame, parent: list[str], child: str, *, rounding: str = "nearest", seed: int = 17
) -> DataFrame:
    """children with size and budget -> + cap, granted. rounding="exact" lowers the cap until the total does not
    pass the budget and hands the rest, one each, to children that have room."""
    caps = fill_levels(children, parent, child)
    out = children.join(caps.select(*parent, "cap", "total"), parent)
    if rounding == "nearest":
        return out.withColumn("granted", F.least("cap", "size").cast("long")).drop("total")
    cap = F.when(F.col("total") > F.col("budget"), F.col("cap") - 1).otherwise(F.col("cap"))
    out = out.withColumn("cap", F.greatest(cap, F.lit(0)).cast("long")).drop("total")
    given = F.least("cap", "size").cast("long")
    out = out.withColumn("open", (F.col("size") > F.col("cap")).cast("int"))
    rest = F.col("budget") - F.sum(given).over(Window.partitionBy(*parent))
    turn = F.row_number().over(Window.partitionBy(*parent, "open").orderBy(priority(seed, F.col(child)), child))
    return out.withColumn("granted", given + ((F.col("open") == 1) & (turn <= rest)).cast("long")).drop("open")


def allocate_tree(
    leaves: DataFrame, levels: list[str], budget, *, rounding: str = "nearest", seed: int = 17, keys: list[str] | None = None
) -> dict[str, DataFrame]:
    """Per level (top first) a table of node, size, budget, cap, granted. leaves: levels and size.
    budget: a number, or a column of leaves where `keys` name independent runs (a grid of budgets in one plan)."""
    keys = keys or []
    out: dict[str, DataFrame] = {}
    base = leaves.withColumn("__all", F.lit(0))
    lead = [*keys, "__all"]
    for i, level in enumerate(levels):
        above = [*lead, *levels[:i]]
        nodes = base.groupBy(*above, level).agg(F.sum("size").cast("long").alias("size"))
        if i == 0:
            if keys:
                tops = base.groupBy(*lead).agg(F.max(budget).cast("long").alias("budget"))
                nodes = nodes.join(F.broadcast(tops), lead)
            else:
                nodes = nodes.withColumn("budget", F.lit(int(budget)).cast("long"))
        else:
            grants = out[levels[i - 1]].select(*above, F.col("granted").alias("budget"))
            nodes = nodes.join(grants, above)
        out[level] = allocate_level(nodes, above, level, rounding=rounding, seed=seed)
    return {k: v.drop("__all") for k, v in out.items()}


def allocate_by_volume(leaves: DataFrame, budget: int, *, size: str = "size", volume: str = "volume") -> DataFrame:
    """leaves + granted: samples in proportion to the volume of each leaf, none above its size. Leaves fill up in the
    order of size / volume; the level is the greatest root of the lines of filled and open leaves. Leaves of no volume
    get nothing."""
    live = leaves.where((F.col(volume) > 0) & (F.col(size) > 0))
    fills = [F.col(size) / F.col(volume)]
    both = staged(sum_before(live, fills, {size: "__full", volume: "__open"}))
    total = both.agg(F.sum(volume).alias("__all"))
    root = (F.lit(float(budget)) - F.col("__full")) / (F.col("__all") - F.col("__open"))
    level = both.join(F.broadcast(total)).agg(F.max(root).alias("__level"))  # one row each
    granted = F.greatest(F.lit(0), F.least(F.col(size), F.floor(F.col("__level") * F.col(volume) + 1e-9))).cast("long")
    out = leaves.join(F.broadcast(level))
    return out.withColumn("granted", F.when(F.col(volume) > 0, F.coalesce(granted, F.lit(0))).otherwise(0).cast("long")).drop("__level")


def draw_points(points: DataFrame, grants: DataFrame, leaf: list[str], *, id_col: str = "point_id", seed: int = 17) -> DataFrame:
    """The `granted` points of least priority in every leaf. A threshold far on the safe side of the wanted
    share drops most points of dense leaves before they are ranked."""
    wanted = grants.select(*leaf, F.col("size").alias("__size"), F.col("granted").alias("__granted")).where("__granted > 0")
    safe = F.col("__granted") + 8 * F.sqrt("__granted") + 16
    near = points.join(wanted, leaf).where(
        (F.col("__granted") >= F.col("__size")) | (uniform(seed, F.col(id_col)) < safe / F.col("__size"))
    )
    turn = Window.partitionBy(*leaf).orderBy(priority(seed, F.col(id_col)), id_col)
    ranked = near.withColumn("draw_rank", F.row_number().over(turn)).where(F.col("draw_rank") <= F.col("__granted"))
    return ranked.drop("__size", "__granted")


def curate(
    points: DataFrame,
    levels: list[str],
    *,
    budget: int | None = None,
    fraction: float | None = None,
    id_col: str = "point_id",
    start: str | None = None,
    rounding: str = "nearest",
    seed: int = 17,
) -> DataFrame:
    """A balanced subset of points that carry their path (levels, top first). start: the first level that
    shares the budget; the ones above are left out."""
    used = levels[levels.index(start) :] if start else levels
    leaves = points.groupBy(*used).agg(F.count("*").alias("size"))
    if budget is None:
        budget = int(round(fraction * points.count()))
    grants = allocate_tree(leaves, used, budget, rounding=rounding, seed=seed)[used[-1]]
    return draw_points(points, grants, used, id_col=id_col, seed=seed)


def curate_percents(points: DataFrame, levels: list[str], percents: tuple[int, ...], *, id_col: str = "point_id", seed: int = 17) -> DataFrame:
    """The subsets that curate() draws for several fractions, in one pass over the points: + run, the percentage."""
    n = points.count()
    budgets = [(p, int(round(p / 100 * n))) for p in percents]
    runs = points.sparkSession.createDataFrame(budgets, "run int, budget long")
    leaves = staged(points.groupBy(*levels).agg(F.count("*").alias("size"))).crossJoin(F.broadcast(runs))  # one row per run
    grants = allocate_tree(leaves, levels, "budget", seed=seed, keys=["run"])[levels[-1]]
    return draw_points(points.crossJoin(F.broadcast(runs.select("run"))), grants, ["run", *levels], id_col=id_col, seed=seed)


def curate_even(points: DataFrame, class_col: str, budget: int, *, id_col: str = "point_id", seed: int = 17) -> DataFrame:
    """An even draw over classes: labels (supervised curation) or the clusters of one flat K-means."""
    return curate(points, [class_col], budget=budget, id_col=id_col, seed=seed)


def select_uniform(points: DataFrame, n: int, *, id_col: str = "point_id", seed: int = 17) -> DataFrame:
    """n points of least priority: keeps the pool's imbalance."""
    return least_priority(points, n, seed, id_col)


def draw_by_distance(assigned: DataFrame, per_leaf: int, within: str = "closest", seed: int = 17) -> DataFrame:
    """Per node: closest or farthest points, random ones, or `spread` (farthest-point order from the closest
    point on, needs vec; one pass per draw, and only one vector per node travels)."""
    if within == "spread":
        rest = staged(assigned.select("point_id", "node", "vec", "dist2", F.col("dist2").alias("__d")))
        first = rest.groupBy("node").agg(F.min(F.struct("dist2", "point_id", "vec")).alias("s"))
        out = None
        for turn in range(per_leaf):
            if turn:
                far = F.max(F.struct("__d", (-F.col("point_id")).alias("k"), "point_id", "dist2", "vec"))
                first = rest.where("__d > 0").groupBy("node").agg(far.alias("s"))
            seeds = staged(first.select("node", "s.point_id", "s.dist2", "s.vec"))
            one = seeds.select("point_id", "node", "dist2")
            out = one if out is None else out.unionByName(one)
            if turn + 1 < per_leaf:
                near = sq_dist(F.col("vec"), F.col("__v"))
                met = rest.join(seeds.select("node", F.col("vec").alias("__v")), "node")
                rest = staged(met.withColumn("__d", F.least("__d", near) if turn else near).drop("__v"))
        return out
    order = {"closest": F.col("dist2"), "farthest": F.col("dist2").desc(), "random": priority(seed, F.col("point_id"))}
    turn = Window.partitionBy("node").orderBy(order[within], "point_id")
    return assigned.withColumn("r", F.row_number().over(turn)).where(F.col("r") <= per_leaf).drop("r")


def prune_copies(df: DataFrame, content: str, id_col: str) -> DataFrame:
    """One row per distinct content: the one of least id."""
    return df.groupBy(F.md5(F.col(content).cast("binary")).alias("digest")).agg(F.min(id_col).alias(id_col), F.count("*").alias("copies"))


def select_uncertain(scores: DataFrame, budget: int) -> DataFrame:
    """Items whose score lies nearest one half."""
    ranked = global_ordinal(scores, [F.abs(F.col("score") - 0.5), F.col("id")], "__rank")
    return ranked.where(F.col("__rank") < budget).drop("__rank")


def saturation(grants: DataFrame) -> DataFrame:
    """+ exhausted, starved."""
    return grants.withColumn("exhausted", F.col("granted") >= F.col("size")).withColumn("starved", F.col("granted") == 0)
