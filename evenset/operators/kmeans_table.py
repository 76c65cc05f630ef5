"""K-means whose centroids are a table, for counts that neither the driver nor a task holds at once.

Centroids are grouped into about sqrt(k) cells. A point visits a cell only if the triangle inequality allows a nearer
centroid in it than the one it is sure to find elsewhere, so assignments stay exact; `nprobe` trades that for a
fixed number of cells. Only cell centres (sqrt(k) x d) and counts per cell travel to the driver and to every task;
points meet the centroids of a cell in groups of at most about `per_task` points, and sums by node stay in a shuffle.
"""

from __future__ import annotations

import numpy as np
import pandas as pd
from pyspark.sql import DataFrame, Window
from pyspark.sql import functions as F

from ..functions.linalg import nearest, plusplus, priority, sq_dist, to_matrix, uniform
from ..sources.tables import staged
from .batching import global_ordinal

ASSIGNED = "point_id long, node long, dist2 double"


def least_priority(points: DataFrame, n: int, seed: int, id_col: str = "point_id") -> DataFrame:
    """The n rows of least priority: a hash threshold on the safe side, then exact ranks in range partitions."""
    total = points.count()
    if n >= total:
        return points
    safe = n + 8 * n**0.5 + 16
    near = points.where(uniform(seed, F.col(id_col)) < safe / total) if safe < total else points
    ranked = global_ordinal(near, [priority(seed, F.col(id_col)), F.col(id_col)], "__rank")
    return ranked.where(F.col("__rank") < n).drop("__rank")


def within_cells(points: DataFrame, centroids: DataFrame, counts: dict[int, int], per_task: int) -> DataFrame:
    """point_id, node, dist2: per row of points (point_id, vec, cell) the nearest of the centroids (node, centroid)
    of its cell. counts: rows of points per cell; a crowded cell is dealt over several groups."""
    spark = points.sparkSession
    rows = [(int(c), -(-n // per_task)) for c, n in counts.items()]
    shares = F.broadcast(spark.createDataFrame(rows, "cell long, shares int"))  # one row per cell
    dealt = points.join(shares, "cell").withColumn("share", F.pmod(F.xxhash64("point_id"), F.col("shares")).cast("int"))
    copied = centroids.join(shares, "cell").withColumn("share", F.explode(F.sequence(F.lit(0), F.col("shares") - 1)))

    def best(left: pd.DataFrame, right: pd.DataFrame) -> pd.DataFrame:
        if not len(left) or not len(right):
            return pd.DataFrame({"point_id": [], "node": [], "dist2": []})
        right = right.sort_values("node")
        at, d = nearest(to_matrix(left["vec"]), to_matrix(right["centroid"]))
        return pd.DataFrame({"point_id": left["point_id"], "node": right["node"].to_numpy()[at], "dist2": d})

    left = dealt.select("cell", "share", "point_id", "vec").groupBy("cell", "share")
    right = copied.select("cell", "share", "node", "centroid").groupBy("cell", "share")
    return left.cogroup(right).applyInPandas(best, ASSIGNED)


def make_cells(centroids: DataFrame, k: int) -> tuple[np.ndarray, np.ndarray, np.ndarray, DataFrame]:
    """(centres, least and greatest distance of a centroid from its centre, centroids with their cell)."""
    from .kmeans import assign, kmeans_fit

    rows = centroids.select(F.col("node").alias("point_id"), F.col("centroid").alias("vec"))
    centres = kmeans_fit(rows, max(1, round(k**0.5)), init="random", max_iter=3).centroids
    of = assign(rows, centres).select(F.col("point_id").alias("node"), F.col("node").alias("cell"), "dist2")
    table = staged(centroids.select("node", "centroid").join(of, "node"))
    near, far = np.full(len(centres), np.inf), np.full(len(centres), -np.inf)
    for r in table.groupBy("cell").agg(F.min("dist2").alias("a"), F.max("dist2").alias("b")).collect():
        near[r["cell"]], far[r["cell"]] = r["a"] ** 0.5, r["b"] ** 0.5
    return centres, near, far, table.drop("dist2")


def assign_table(points: DataFrame, centroids: DataFrame, k: int, *, nprobe: int | None = None, per_task: int = 8192) -> DataFrame:
    """point_id, node, dist2 of the nearest centroid. nprobe: only so many cells, those with the nearest centres."""
    centres, near, far, table = make_cells(centroids, k)
    size = (centres**2).sum(axis=1)

    def hits(x: np.ndarray) -> tuple[np.ndarray, np.ndarray]:
        d = np.sqrt(np.maximum(size[None, :] - 2 * (x @ centres.T) + (x**2).sum(axis=1)[:, None], 0))
        if nprobe is None:
            reach = (d + near[None, :]).min(axis=1)  # a centroid at most this far exists
            least = np.maximum(d - far[None, :], near[None, :] - d)
            return np.nonzero(least <= reach[:, None] * (1 + 1e-7) + 1e-7)
        live = np.where(np.isfinite(near)[None, :], d, np.inf)
        cells = np.argsort(live, axis=1, kind="stable")[:, : min(nprobe, int(np.isfinite(near).sum()))]
        return np.repeat(np.arange(len(x)), cells.shape[1]), cells.ravel()

    def count(batches):
        held = np.zeros(len(centres), np.int64)
        for pdf in batches:
            for at in range(0, len(pdf), 4096):
                held += np.bincount(hits(to_matrix(pdf["vec"].iloc[at : at + 4096]))[1], minlength=len(held))
        live = np.flatnonzero(held)
        yield pd.DataFrame({"cell": live, "n": held[live]}, dtype="int64")

    def probe(batches):
        for pdf in batches:
            for at in range(0, len(pdf), 4096):
                part = pdf.iloc[at : at + 4096]
                rows, cells = hits(to_matrix(part["vec"]))
                yield pd.DataFrame({"point_id": part["point_id"].to_numpy()[rows], "vec": part["vec"].to_numpy()[rows], "cell": cells})

    counted = points.select("vec").mapInPandas(count, "cell long, n long").groupBy("cell").agg(F.sum("n").alias("n"))
    counts = {r["cell"]: r["n"] for r in counted.collect()}  # one row per cell
    probes = points.select("point_id", "vec").mapInPandas(probe, "point_id long, vec array<double>, cell long")
    met = within_cells(probes, table, counts, per_task)
    best = met.groupBy("point_id").agg(F.min(F.struct("dist2", "node")).alias("b"))
    return best.select("point_id", F.col("b.node").alias("node"), F.col("b.dist2").alias("dist2"))


def sums_by_node(rows: DataFrame, dim: int) -> DataFrame:
    """node, n, sse, s of rows (node, dist2, vec): sums within every batch, then by node in a shuffle."""

    def run(batches):
        for pdf in batches:
            if len(pdf):
                at, of = np.unique(pdf["node"].to_numpy(), return_inverse=True)
                order = np.argsort(of, kind="stable")
                first = np.flatnonzero(np.diff(of[order], prepend=-1))
                sums = np.add.reduceat(to_matrix(pdf["vec"])[order], first)
                s = pd.Series(list(sums), dtype=object)
                yield pd.DataFrame({"node": at, "n": np.bincount(of).astype(float), "sse": np.bincount(of, pdf["dist2"]), "s": s})

    parts = rows.select("node", "dist2", "vec").mapInPandas(run, "node long, n double, sse double, s array<double>")
    total = F.array(*[F.sum(F.get("s", F.lit(j))) for j in range(dim)])
    return parts.groupBy("node").agg(F.sum("n").alias("n"), F.sum("sse").alias("sse"), total.alias("s"))


def seed_grouped(points: DataFrame, k: int, seed: int = 1, *, per_seed: int = 8, most: int = 2000) -> DataFrame:
    """node, centroid: k seeds by D-squared picks inside about sqrt(k) groups. A group gets seeds in proportion to its
    squared distances, drawn from `per_seed` sampled points a seed, at most `most` seeds a task."""
    from .kmeans import assign, kmeans_fit

    n = points.count()
    k = min(k, n)
    centres = kmeans_fit(points, max(1, round(k**0.5)), init="random", max_iter=2, seed=seed).centroids
    at = staged(assign(points, centres))
    held = at.groupBy("node").agg(F.count("*").alias("n"), F.sum("dist2").alias("m")).orderBy("node").collect()
    size, mass = (np.array([r[c] for r in held], float) for c in ("n", "m"))
    give = np.minimum(size, 1.0)  # each group one, or its points would lie far from all seeds
    while (left := k - int(give.sum())) > 0:  # by mass, no group above its size; the rest again among the others
        share = np.where(give < size, mass + 1e-300 + mass.sum() * 1e-9 + (mass.sum() == 0) * size, 0)
        want = share / share.sum() * left
        more = np.floor(want)
        more[np.argsort(more - want, kind="stable")[: left - int(more.sum())]] += 1
        give = np.minimum(give + more, size)
    plan = [(int(r["node"]), int(g), -(-int(g) // most)) for r, g in zip(held, give) if g]
    plan = points.sparkSession.createDataFrame(plan, "node long, seeds int, tasks int")
    turn = Window.partitionBy("node", "task").orderBy(priority(seed, F.col("point_id")), "point_id")
    rows = at.join(F.broadcast(plan), "node").withColumn("task", F.pmod(F.xxhash64("point_id"), F.col("tasks")).cast("int"))
    rows = rows.withColumn("r", F.row_number().over(turn)).where(F.col("r") <= per_seed * F.ceil(F.col("seeds") / F.col("tasks")) + 8)

    def pick(pdf: pd.DataFrame) -> pd.DataFrame:
        pdf = pdf.sort_values("r", ignore_index=True)
        seeds, tasks, task = (int(pdf[c].iloc[0]) for c in ("seeds", "tasks", "task"))
        mine = seeds // tasks + (task < seeds % tasks)
        rng = np.random.default_rng([seed, int(pdf["node"].iloc[0]) + 1, task])
        got = plusplus(to_matrix(pdf["vec"]), mine, rng)
        return pd.DataFrame({"node": pdf["node"].iloc[0], "task": task, "i": np.arange(len(got)), "centroid": list(got)})

    drawn = points.join(rows.select("point_id", "node", "seeds", "tasks", "task", "r"), "point_id")
    seeds = drawn.groupBy("node", "task").applyInPandas(pick, "node long, task int, i long, centroid array<double>")
    seeds = global_ordinal(seeds, [F.col("node"), F.col("task"), F.col("i")])
    return seeds.select(F.col("ordinal").alias("node"), "centroid")


def fit_table(
    points: DataFrame, k: int, dim: int, *, seed: int, init, max_iter: int, tol: float, empty: str
) -> tuple[DataFrame, int, list[float]]:
    """(node and centroid, how many, history) by Lloyd steps over a table of centroids."""
    if isinstance(init, str):
        if init == "random":
            chosen = global_ordinal(least_priority(points, k, seed), [priority(seed, F.col("point_id")), F.col("point_id")])
            init = chosen.select(F.col("ordinal").alias("node"), F.col("vec").alias("centroid"))
        else:
            init = seed_grouped(points, k, seed)
    table = staged(init.select("node", "centroid"))
    k, history = table.count(), []
    for _ in range(max_iter):
        at = staged(assign_table(points, table, k))
        sums = sums_by_node(points.join(at, "point_id"), dim)
        mean = F.transform("s", lambda x: x / F.col("n"))
        new = table.join(sums, "node", "left").select(
            "node", F.col("centroid").alias("old"), F.coalesce(mean, "centroid").alias("centroid"), F.col("n").isNull().alias("empty"), "sse"
        )
        new = staged(new)
        if empty == "farthest" and (lost := new.where("empty").count()):
            far = global_ordinal(at, [-F.col("dist2"), F.col("point_id")]).where(F.col("ordinal") < lost)
            far = far.join(points, "point_id").select("ordinal", F.col("vec").alias("far"))
            slots = global_ordinal(new.where("empty").select("node"), [F.col("node")]).join(far, "ordinal")
            new = staged(new.join(slots.select("node", "far"), "node", "left").withColumn("centroid", F.coalesce("far", "centroid")))
        seen = new.agg(F.sum("sse").alias("sse"), F.max(sq_dist(F.col("old"), F.col("centroid"))).alias("moved")).first()
        history.append(seen["sse"] or 0.0)
        table = new.select("node", "centroid")
        if (seen["moved"] or 0.0) < tol:
            break
    return table, k, history
