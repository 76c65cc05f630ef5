"""K-means over points: seeding, assignment strategies, Lloyd steps, resampling.

Up to DRIVER_BYTES of centroids are one array on the driver and in every task; more are a table (kmeans_table),
with the same Lloyd steps. Defined cases: null vectors take no part; without points there are no centroids, and
with fewer points than clusters as many as there are points; the order of rows does not matter.
"""

from __future__ import annotations

from dataclasses import dataclass, field

import numpy as np
import pandas as pd
import pyarrow as pa
from pyspark.sql import DataFrame, Window
from pyspark.sql import functions as F

from ..functions.linalg import (
    collect_matrix, list_matrix, lloyd, matrix_frame, nearest, plusplus, priority, screen, sq_dist, to_matrix, uniform,
)
from ..sources.tables import staged
from .kmeans_table import assign_table, fit_table, seed_grouped

BROADCAST_BYTES = DRIVER_BYTES = 256 << 20


@dataclass
class KMeansModel:
    """centroids: an array, or None where they are a table (node, centroid) of k rows."""

    centroids: np.ndarray | None
    history: list[float] = field(default_factory=list)
    table: DataFrame | None = None
    k: int = 0

    def assign(self, points: DataFrame) -> DataFrame:
        if self.centroids is None:
            return assign_table(points, self.table, self.k)
        return assign(points, self.centroids)


def priority_sample(points: DataFrame, rows: int, seed: int) -> np.ndarray:
    """At most `rows` vectors, those of least priority: a repeatable sample, collected, so for the driver's own bounds.
    least_priority draws without such a bound."""
    total, near, order = points.count(), points, [priority(seed, F.col("point_id")), F.col("point_id")]
    safe = rows + 8 * rows**0.5 + 16
    if safe < total:  # or every task would send so many rows to the driver
        near = points.where(uniform(seed, F.col("point_id")) < safe / total)
        near = near if near.count() >= rows else points
    return collect_matrix(near.orderBy(*order).limit(rows).select("vec"), "vec")[1]


def seed_random(points: DataFrame, k: int, seed: int = 1) -> np.ndarray:
    return priority_sample(points, k, seed)


def seed_plusplus(points: DataFrame, k: int, seed: int = 1, sample_rows: int = 20000) -> np.ndarray:
    """D-squared picks from a sample on the driver; for more seeds than a fourth of it, in tasks, inside groups."""
    if 4 * k > sample_rows:
        return collect_matrix(seed_grouped(points, k, seed).orderBy("node"), "centroid")[1]
    return plusplus(priority_sample(points, sample_rows, seed), k, np.random.default_rng(seed))


def seed_parallel(points: DataFrame, k: int, seed: int = 1, rounds: int = 5, factor: float = 2.0) -> np.ndarray:
    """Oversampled rounds: each keeps points with chance factor * k * d2 / sum(d2); at the end the candidates,
    weighted by whom they attract, are thinned by D-squared picks."""
    chosen = priority_sample(points, 1, seed)
    for r in range(rounds):
        far = assign(points, chosen)
        total = far.agg(F.sum("dist2")).first()[0] or 0.0
        if total <= 0:
            break
        keep = far.where(uniform(seed + 1 + r, F.col("point_id")) < factor * k * F.col("dist2") / total)
        # factor * k rows are expected, and never many more: each is kept by chance on its own
        found = points.join(keep.select("point_id"), "point_id", "left_semi").orderBy("point_id").select("vec")
        found = to_matrix([x["vec"] for x in found.collect()])
        if len(found):
            chosen = np.vstack([chosen, found])
    sizes = {r["node"]: r["count"] for r in assign(points, chosen).groupBy("node").count().collect()}
    weights = np.array([sizes.get(i, 0) for i in range(len(chosen))], float) + 1e-9
    return plusplus(chosen, k, np.random.default_rng(seed), weights)


def seed_passes(points: DataFrame, k: int, seed: int = 1, how: str = "race") -> tuple[list[int], np.ndarray]:
    """Ids and vectors of k seeds, one pass over all points per seed.

    farthest: the point farthest from the seeds so far. race: an exact D-squared draw over all points, as the
    least of independent exponential times -ln(u) / d2 is drawn in proportion to d2; no prefix sums are needed."""
    first = points.orderBy(priority(seed, F.col("point_id")), "point_id").select("point_id", "vec").first()
    ids, vecs = [first["point_id"]], [first["vec"]]
    for turn in range(k - 1):
        far = assign(points, to_matrix(vecs)).where("dist2 > 0")
        u = uniform(seed + 1 + turn, F.col("point_id")) + 0.5 / (1 << 32)
        rank = -F.col("dist2") if how == "farthest" else -F.log(u) / F.col("dist2")
        best = far.agg(F.min(F.struct(rank.alias("r"), "point_id")).alias("b")).first()["b"]
        if best is None:
            break
        ids.append(best["point_id"])
        vecs.append(points.where(F.col("point_id") == best["point_id"]).select("vec").first()["vec"])
    return ids, to_matrix(vecs)


def centroid_frame(spark, centroids: np.ndarray) -> DataFrame:
    return matrix_frame(spark, {"node": np.arange(len(centroids))}, "centroid", centroids)


def assign(points: DataFrame, centroids: np.ndarray, *, strategy: str = "auto", nprobe: int = 4, blocks: int = 4) -> DataFrame:
    """point_id, node, dist2 of the nearest centroid (ties: least node).

    expr: Catalyst only; broadcast_gemm: one Arrow pass with all centroids, up to BROADCAST_BYTES; blocked:
    centroid blocks one after another, exact; coarse: only the nprobe nearest cells of centroids."""
    points = points.where("vec is not null")
    if not len(centroids):
        return points.select("point_id", F.lit(0).cast("long").alias("node"), F.lit(0.0).alias("dist2")).limit(0)
    if strategy == "auto":
        strategy = "broadcast_gemm" if centroids.nbytes <= BROADCAST_BYTES else "blocked"
    schema = "point_id long, node long, dist2 double"
    if strategy == "expr":
        c = centroid_frame(points.sparkSession, centroids)
        pairs = points.crossJoin(F.broadcast(c)).select("point_id", "node", sq_dist(F.col("vec"), F.col("centroid")).alias("d"))
        best = pairs.groupBy("point_id").agg(F.min(F.struct("d", "node")).alias("b"))
        return best.select("point_id", F.col("b.node").alias("node"), F.col("b.d").alias("dist2"))
    if strategy == "blocked":
        parts = np.array_split(np.arange(len(centroids)), min(blocks, len(centroids)))
        each = [
            assign(points, centroids[p], strategy="broadcast_gemm").withColumn("node", F.col("node") + int(p[0]))
            for p in parts
        ]
        every = each[0]
        for e in each[1:]:
            every = every.unionByName(e)
        best = every.groupBy("point_id").agg(F.min(F.struct("dist2", "node")).alias("b"))
        return best.select("point_id", F.col("b.node").alias("node"), F.col("b.dist2").alias("dist2"))
    if strategy == "coarse":
        cells, of, _, _ = lloyd(centroids, plusplus(centroids, max(1, int(np.sqrt(len(centroids)))), np.random.default_rng(0)), 10)

        def probe(x: np.ndarray, centroids: np.ndarray, known=None) -> tuple[np.ndarray, np.ndarray]:
            d = (cells**2).sum(1)[None] - 2 * x @ cells.T
            probes = np.argsort(d, axis=1)[:, :nprobe]
            node, best = np.full(len(x), -1), np.full(len(x), np.inf)
            for cell in range(len(cells)):
                rows, mine = np.flatnonzero((probes == cell).any(axis=1)), np.flatnonzero(of == cell)
                if len(rows) and len(mine):
                    at, dist = nearest(x[rows], centroids[mine])
                    better = dist < best[rows]
                    node[rows[better]], best[rows[better]] = mine[at[better]], dist[better]
            return node, best

        kernel = probe
    else:
        kernel = nearest

    held = points.sparkSession.sparkContext.broadcast(centroids)  # goes when the result is forgotten

    def run(batches):
        centroids, known = held.value, None
        for b in batches:
            if b.num_rows:
                x = list_matrix(b.column("vec"))
                known = known or screen(centroids)
                node, d = kernel(x, centroids, known=known)
                yield pa.record_batch([b.column("point_id").cast("int64"), pa.array(node, "int64"), pa.array(d)], ["point_id", "node", "dist2"])

    return points.select("point_id", "vec").mapInArrow(run, schema)


def _partials(points: DataFrame, centroids: np.ndarray) -> tuple[np.ndarray, np.ndarray, float]:
    """Sums, counts and total squared distance; one row per task and node is shuffled, k x d come back."""
    dim = centroids.shape[1]
    held = points.sparkSession.sparkContext.broadcast(centroids)

    def run(batches):
        centroids, known = held.value, None
        sums, mass, sse = np.zeros_like(centroids), np.zeros(len(centroids)), np.zeros(len(centroids))
        for b in batches:
            if b.num_rows:
                x = list_matrix(b.column("vec"))
                known = known or screen(centroids)
                at, d = nearest(x, centroids, known=known)
                mass += np.bincount(at, minlength=len(centroids))
                sse += np.bincount(at, d, len(centroids))
                order = np.argsort(at, kind="stable")
                first = np.flatnonzero(np.diff(at[order], prepend=-1))
                sums[at[order][first]] += np.add.reduceat(x[order], first)
        live = np.flatnonzero(mass)
        for i in range(0, len(live), 4096):
            some = live[i : i + 4096]
            s = pa.ListArray.from_arrays(np.arange(len(some) + 1, dtype=np.int32) * dim, pa.array(sums[some].ravel()))
            yield pa.record_batch([pa.array(some, "int64"), pa.array(mass[some]), pa.array(sse[some]), s], ["node", "n", "sse", "s"])

    vecs = points.select("vec")
    if len(centroids) > 1024:  # with many nodes a task has a row for nearly every point: no more tasks than cores
        vecs = vecs.coalesce(points.sparkSession.sparkContext.defaultParallelism)
    parts = vecs.mapInArrow(run, "node long, n double, sse double, s array<double>")
    merged = parts.groupBy("node").agg(
        F.sum("n").alias("n"), F.sum("sse").alias("sse"), F.array(*[F.sum(F.get("s", F.lit(j))) for j in range(dim)]).alias("s")
    )
    sums, mass = np.zeros_like(centroids), np.zeros(len(centroids))
    rows, vecs = collect_matrix(merged, "s")
    held.destroy()  # or each step would leave its centroids with the driver and all executors
    if rows.num_rows:
        at = rows.column("node").to_numpy()
        sums[at], mass[at] = vecs, rows.column("n").to_numpy()
    return sums, mass, float(rows.column("sse").to_numpy().sum())


def kmeans_fit(
    points: DataFrame, k: int, *, seed: int = 1, init="plusplus", max_iter: int = 10, tol: float = 1e-6, empty: str = "keep",
    driver_bytes: int = DRIVER_BYTES,
) -> KMeansModel:
    """Lloyd's algorithm. init: plusplus, parallel, random, or centroids as an array or a table (node, centroid).
    Centroids of more than driver_bytes are kept as a table; seeds other than random are then drawn in groups."""
    points = points.where("vec is not null")
    one = points.select(F.size("vec").alias("d")).first()
    if one is None:
        return KMeansModel(np.zeros((0, 1)))
    if isinstance(init, DataFrame) or 8 * k * one["d"] > driver_bytes:
        if isinstance(init, np.ndarray):
            init = centroid_frame(points.sparkSession, init)
        table, k, history = fit_table(points, k, one["d"], seed=seed, init=init, max_iter=max_iter, tol=tol, empty=empty)
        return KMeansModel(None, history, table, k)
    start = {"plusplus": seed_plusplus, "parallel": seed_parallel, "random": seed_random}
    c = start[init](points, k, seed) if isinstance(init, str) else np.array(init, float)
    history = []
    for _ in range(max_iter):
        sums, mass, sse = _partials(points, c)
        history.append(sse)
        new = sums  # in place: k x d may be a good part of the driver's memory
        new /= np.maximum(mass, 1)[:, None]
        new[mass == 0] = c[mass == 0]
        if empty == "farthest" and (mass == 0).any():
            far = assign(points, c).orderBy(F.desc("dist2"), "point_id").limit(int((mass == 0).sum()))
            rows = points.join(F.broadcast(far.select("point_id", "dist2")), "point_id").orderBy(F.desc("dist2"), "point_id").select("vec").collect()
            for slot, r in zip(np.flatnonzero(mass == 0), rows):
                new[slot] = r["vec"]
        moved = max(float(((new[i : i + 4096] - c[i : i + 4096]) ** 2).sum(axis=1).max()) for i in range(0, len(c), 4096))
        c = new
        if moved < tol:
            break
    return KMeansModel(c, history)


def block_neighbours(points: DataFrame, queries: DataFrame, k: int, *, query_block: int = 256, row_block: int = 4096) -> DataFrame:
    """seed, point_id, dist2: the k nearest other points of every query. Query blocks meet row blocks, each pair of
    blocks keeps k a query; work is queries x rows."""
    nq, nr = (max(1, -(-df.count() // size)) for df, size in ((queries, query_block), (points, row_block)))

    def block(n: int):
        return F.pmod(F.xxhash64("point_id"), F.lit(n)).cast("int")

    def every(n: int):
        return F.explode(F.sequence(F.lit(0), F.lit(n - 1)))

    q = queries.select("point_id", "vec", block(nq).alias("qb")).withColumn("rb", every(nr))
    p = points.select("point_id", "vec", block(nr).alias("rb")).withColumn("qb", every(nq))

    def best(left: pd.DataFrame, right: pd.DataFrame) -> pd.DataFrame:
        out = []
        if len(left) and len(right):
            x, y, ids = to_matrix(left["vec"]), to_matrix(right["vec"]), right["point_id"].to_numpy()
            d = np.zeros((len(x), len(y)))
            for j in range(x.shape[1]):  # summed in the order of components, as in SQL
                d += (y[None, :, j] - x[:, None, j]) ** 2
            for seed, row in zip(left["point_id"], d):
                order = np.lexsort((ids, row))
                out += [(seed, ids[i], row[i]) for i in order[ids[order] != seed][:k]]
        return pd.DataFrame(out, columns=["seed", "point_id", "dist2"])

    near = q.groupBy("qb", "rb").cogroup(p.groupBy("qb", "rb")).applyInPandas(best, "seed long, point_id long, dist2 double")
    turn = Window.partitionBy("seed").orderBy("dist2", "point_id")
    return near.withColumn("r", F.row_number().over(turn)).where(F.col("r") <= k).drop("r")


def closest_per_node(assigned: DataFrame, per_node: int) -> DataFrame:
    """The per_node points nearest to each centroid."""
    turn = Window.partitionBy("node").orderBy("dist2", "point_id")
    return assigned.withColumn("r", F.row_number().over(turn)).where(F.col("r") <= per_node)


def resample_refine(points: DataFrame, model: KMeansModel, *, rounds: int = 1, per_cluster: int = 10, max_iter: int = 5) -> KMeansModel:
    """Refit on the points nearest to each centroid, which flattens dense regions, then go on from there."""
    for _ in range(rounds):
        flat = closest_per_node(model.assign(points), per_cluster).select("point_id")
        sample = staged(points.join(flat, "point_id", "left_semi"))
        init = model.table if model.centroids is None else model.centroids
        model = kmeans_fit(sample, model.k or len(init), init=init, max_iter=max_iter)
    return model
