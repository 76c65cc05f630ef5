"""The cluster tree: levels of K-means, each over the centroids of the level below.

A level whose centroids are few enough for the driver is an array there; a larger one is a table (node, parent,
centroid) that no driver or task holds as a whole, and the same K-means runs over it. Defined cases: null vectors take
no part; clusters without points do not become nodes; without points there is no tree (ValueError).
"""

from __future__ import annotations

from collections.abc import Callable
from dataclasses import dataclass, field

import numpy as np
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from ..functions.linalg import collect_matrix, lloyd, long_frame, matrix_frame, nearest, plusplus
from ..sources.tables import spread, staged
from .batching import global_ordinal
from .kmeans import DRIVER_BYTES, KMeansModel, centroid_frame, kmeans_fit, resample_refine
from .kmeans_table import within_cells

# Ratios between neighbouring levels of the two published tree shapes.
NARROW, WIDE = (100.0, 100.0, 350 / 62), (35.0, 10.0, 10000 / 2048)
# Fewest top nodes that leave something to balance and to stratify by, where the leaves allow as many.
LEAST_TOP = {"narrow": 7, "wide": 32}


def level_counts(n: int, depth: int = 4, leaf_fraction: float = 0.01, top: int = 62, shape: str = "geometric") -> list[int]:
    """Clusters per level, leaves first: a fixed share of n.

    narrow, wide: the published ratios between levels, from the n at which they leave LEAST_TOP top nodes; below
    it all ratios are taken to one power, so that so many (at most half the leaves) remain instead of one."""
    leaves = max(1, round(n * leaf_fraction))
    if shape != "geometric":
        ratios = np.array((NARROW if shape == "narrow" else WIDE)[: depth - 1])
        least = min(LEAST_TOP[shape], max(1, leaves // 2))
        if leaves < least * ratios.prod():
            ratios = ratios ** (np.log(leaves / least) / np.log(ratios.prod()))
        return [max(1, round(x)) for x in leaves / np.cumprod([1.0, *ratios])]
    step = (min(top, leaves) / leaves) ** (1 / max(depth - 1, 1))
    return [max(1, round(leaves * step**i)) for i in range(depth)]


@dataclass
class ClusterTree:
    """Levels 0 (leaves) to top. centroids[l]: an array or None; parent[l]: node of level l + 1 or None; tables[l]: node,
    parent, centroid, always. leaf_of: point_id, c1, dist2."""

    centroids: list[np.ndarray | None]
    parent: list[np.ndarray | None]
    leaf_of: DataFrame
    large: dict[int, DataFrame] = field(default_factory=dict)
    counts: list[int] = field(default_factory=list)

    def __post_init__(self):
        self.counts = self.counts or [len(c) for c in self.centroids]

    @property
    def depth(self) -> int:
        return len(self.centroids)

    def table(self, level: int) -> DataFrame:
        """node, parent (-1 at the top), centroid of a level, 0 for the leaves."""
        if self.centroids[level] is None:
            return self.large[level]
        return matrix_frame(self.leaf_of.sparkSession, self._ids(level), "centroid", self.centroids[level])

    def _ids(self, level: int) -> dict[str, np.ndarray]:
        up = self.parent[level] if level + 1 < self.depth else np.full(self.counts[level], -1)
        return {"node": np.arange(self.counts[level]), "parent": up}

    def links(self, level: int) -> DataFrame:
        """node and parent of a level; no centroid leaves the driver for it."""
        if self.centroids[level] is None:
            return self.large[level].select("node", "parent")
        return long_frame(self.leaf_of.sparkSession, self._ids(level))

    def path_table(self) -> DataFrame:
        """c1 .. cL of every leaf."""
        if any(p is None for p in self.parent):
            out = self.links(0).select(F.col("node").alias("c1"), F.col("parent").alias("c2"))
            for level in range(1, self.depth - 1):
                up = self.links(level).select(F.col("node").alias(f"c{level + 1}"), F.col("parent").alias(f"c{level + 2}"))
                out = out.join(up, f"c{level + 1}")
            return out.select(*[f"c{i + 1}" for i in range(self.depth)])
        cols = [np.arange(self.counts[0])]
        for p in self.parent:
            cols.append(p[cols[-1]])
        return long_frame(self.leaf_of.sparkSession, {f"c{i + 1}": c for i, c in enumerate(cols)})

    def paths(self) -> DataFrame:
        """point_id and path; Spark broadcasts the table of leaves if it is small enough."""
        return self.leaf_of.select("point_id", "c1").join(self.path_table(), "c1")

    def sizes(self, level: int, subset: DataFrame | None = None) -> DataFrame:
        """node, n for every node of a level, 0 where the subset has none; log10 of n."""
        paths = self.paths() if subset is None else self.paths().join(subset.select("point_id"), "point_id", "left_semi")
        held = paths.groupBy(F.col(f"c{level}").alias("node")).agg(F.count("*").alias("n"))
        every = self.leaf_of.sparkSession.range(self.counts[level - 1]).withColumnRenamed("id", "node")
        out = every.join(held, "node", "left").withColumn("n", F.coalesce("n", F.lit(0)))
        return out.withColumn("log_n", F.log10(F.greatest("n", F.lit(1))))

    def nodes(self, centroids: bool = True) -> DataFrame:
        """level (leaves 1), node, parent, centroid (if wanted), n_children of all nodes."""
        out = None
        for level in range(self.depth):
            t = (self.table(level) if centroids else self.links(level)).withColumn("level", F.lit(level + 1))
            if level:
                kids = self.links(level - 1).groupBy(F.col("parent").alias("node")).agg(F.count("*").alias("n_children"))
                t = t.join(kids, "node", "left")
            else:
                t = t.withColumn("n_children", F.lit(0).cast("long"))
            t = t.select("level", "node", "parent", *["centroid"] * centroids, "n_children")
            out = t if out is None else out.unionByName(t)
        return out

    def subtree(self, top_level: int, node: int) -> "ClusterTree":
        """The tree below one node: its leaves and points, nodes numbered anew."""
        if any(c is None for c in self.centroids[: top_level]):
            raise ValueError("cut a tree whose levels are arrays")
        keep = [np.array([node])]
        for level in range(top_level - 2, -1, -1):
            keep.insert(0, np.flatnonzero(np.isin(self.parent[level], keep[0])))
        centroids = [self.centroids[level][k] for level, k in enumerate(keep)]
        parent = [np.searchsorted(keep[level + 1], self.parent[level][keep[level]]) for level in range(top_level - 1)]
        spark = self.leaf_of.sparkSession
        new = spark.createDataFrame([(int(o), i) for i, o in enumerate(keep[0])], "c1 long, new long")
        leaf_of = self.leaf_of.join(new, "c1").select("point_id", F.col("new").alias("c1"), "dist2")
        return ClusterTree(centroids, parent, leaf_of)

    def truncate(self, top_level: int) -> "ClusterTree":
        """The lower levels only: a tree of less depth."""
        large = {k: v for k, v in self.large.items() if k < top_level}
        return ClusterTree(self.centroids[:top_level], self.parent[: top_level - 1], self.leaf_of, large, self.counts[:top_level])

    def route(self, points: DataFrame, mode: str = "leaf") -> DataFrame:
        """Unseen points to leaves: leaf compares with all leaves, greedy walks down from the top."""
        if mode == "leaf":
            found = KMeansModel(self.centroids[0], table=self.large.get(0), k=self.counts[0]).assign(points)
            return found.withColumnRenamed("node", "c1")
        if any(c is None for c in self.centroids):
            return self._walk(points)
        centroids, parent = self.centroids, self.parent

        def run(batches):
            import pandas as pd

            from ..functions.linalg import to_matrix

            for pdf in batches:
                x = to_matrix(pdf["vec"])
                at, d = nearest(x, centroids[-1]) if len(x) else (np.zeros(0, int), np.zeros(0))
                for level in range(len(centroids) - 2, -1, -1):
                    new = np.zeros(len(x), int)
                    for node in np.unique(at):
                        rows, kids = np.flatnonzero(at == node), np.flatnonzero(parent[level] == node)
                        near, dist = nearest(x[rows], centroids[level][kids])
                        new[rows], d[rows] = kids[near], dist
                    at = new
                yield pd.DataFrame({"point_id": pdf["point_id"], "c1": at, "dist2": d})

        return points.where("vec is not null").select("point_id", "vec").mapInPandas(run, "point_id long, c1 long, dist2 double")

    def _walk(self, points: DataFrame, per_task: int = 8192) -> DataFrame:
        """Greedy routing level by level: points meet the children of the node they have reached."""
        top = self.depth - 1
        points = points.where("vec is not null").select("point_id", "vec")
        at = KMeansModel(self.centroids[top], table=self.large.get(top), k=self.counts[top]).assign(points)
        for level in range(top - 1, -1, -1):
            at = staged(at)
            here = points.join(at.select("point_id", F.col("node").alias("cell")), "point_id")
            counts = {r["node"]: r["count"] for r in at.groupBy("node").count().collect()}  # one row per node above
            at = within_cells(here, self.table(level).select("node", "centroid", F.col("parent").alias("cell")), counts, per_task)
        return at.withColumnRenamed("node", "c1")

    def save(self, path: str) -> None:
        self.nodes().write.partitionBy("level").parquet(f"{path}/nodes")
        self.leaf_of.write.parquet(f"{path}/leaf_of")


def load_tree(spark, path: str, driver_bytes: int = DRIVER_BYTES) -> ClusterTree:
    nodes = spark.read.parquet(f"{path}/nodes")
    held = nodes.groupBy("level").agg(F.count("*").alias("n"), F.first(F.size("centroid")).alias("d")).orderBy("level").collect()
    centroids, parent, large = [], [], {}
    for r in held:
        level = nodes.where(F.col("level") == r["level"]).select("node", "parent", "centroid")
        if 8 * r["n"] * r["d"] > driver_bytes:
            large[r["level"] - 1] = level
            centroids.append(None)
            parent.append(None)
            continue
        rows, c = collect_matrix(level.orderBy("node"), "centroid")
        centroids.append(c)
        parent.append(rows.column("parent").to_numpy().astype(int))
    return ClusterTree(centroids, parent[:-1], spark.read.parquet(f"{path}/leaf_of"), large, [r["n"] for r in held])


def drop_empty(centroids: np.ndarray, at: np.ndarray) -> tuple[np.ndarray, np.ndarray]:
    live, new = np.unique(at, return_inverse=True)
    return centroids[live], new


def resample_array(below: np.ndarray, c: np.ndarray, rounds: int, per_cluster: int = 10, max_iter: int = 5) -> np.ndarray:
    """Refit on the rows nearest to each centroid, as resample_refine does for points."""
    for _ in range(rounds):
        at, d = nearest(below, c)
        order = np.lexsort((d, at))
        first = np.searchsorted(at[order], at[order])  # where each cluster begins
        c = lloyd(below[order[np.arange(len(order)) - first < per_cluster]], c, max_iter)[0]
    return c


def _level(points: DataFrame, model: KMeansModel) -> tuple[np.ndarray | None, DataFrame | None, int, DataFrame]:
    """(centroids as array or table, how many, point_id and node and dist2) of the clusters that have points."""
    at = staged(model.assign(points))
    live = at.select("node").distinct()
    if model.centroids is None:
        new = staged(global_ordinal(live, [F.col("node")]))
        table = new.join(model.table, "node").select(F.col("ordinal").alias("node"), "centroid")
        k, array = new.count(), None
    else:
        nodes = np.sort(live.toArrow().column("node").to_numpy())
        new = long_frame(points.sparkSession, {"node": nodes, "ordinal": np.arange(len(nodes))})
        table, k, array = None, len(nodes), model.centroids[nodes]
    return array, table, k, at.join(new, "node").select("point_id", F.col("ordinal").alias("node"), "dist2")


def fit_level(
    points: DataFrame, k: int, *, seed: int = 1, max_iter: int = 5, resample_rounds: int = 0, driver_bytes: int = DRIVER_BYTES
) -> tuple[np.ndarray | None, DataFrame | None, int, DataFrame]:
    """A level over points that stay in a table: what _level says of it, with the assignment written."""
    model = kmeans_fit(points, k, seed=seed, max_iter=max_iter, driver_bytes=driver_bytes)
    if resample_rounds:
        model = resample_refine(points, model, rounds=resample_rounds)
    array, table, k, at = _level(points, model)
    return array, table, k, staged(at)


def build_tree(
    points: DataFrame, counts: list[int] | Callable[[int], list[int]], *, seed: int = 1, max_iter: int = 5,
    resample_rounds: int = 0, centroid_weight: str = "one", driver_bytes: int = DRIVER_BYTES, stage: bool = True, leaves: tuple | None = None,
) -> ClusterTree:
    """K-means over the points, then over the centroids of the level below, each counting once whatever its population
    (centroid_weight="population" is the contrast, for levels below which centroids are arrays). Each level is resampled
    resample_rounds times. counts may be a function of the number of points. Levels of more than driver_bytes are tables.
    stage=False: the points are cheap to read again, as unpacked ones are, and not written once more. leaves: fit_level
    of the points with the same settings, for trees that share their leaves."""
    points = points.where("vec is not null")
    points = staged(spread(points)) if stage else points
    n = points.count()
    if n == 0:
        raise ValueError("no points to build a tree from")
    counts = counts(n) if callable(counts) else counts
    centroids, parents, large, held = [], [], {}, []
    below, weight, leaf_of = None, None, None  # below: the last level as an array, or None
    level_points = points
    for level, k in enumerate(counts):
        if level and below is not None:
            w = weight if centroid_weight == "population" else None
            start = plusplus(below, min(k, len(below)), np.random.default_rng(seed + level), w)
            c, at, _, _ = lloyd(below, start, 15, weights=w)
            if resample_rounds and w is None:
                c = lloyd(below, resample_array(below, c, resample_rounds), 1)[0]
                at = nearest(below, c)[0]
            c, at = drop_empty(c, at)
            centroids.append(c)
            parents.append(at)
            held.append(len(c))
            weight = np.bincount(at, weight, len(c)) if weight is not None else None
            below = c
            continue
        if level and centroid_weight == "population":
            raise ValueError("population weights need the centroids below as an array: raise driver_bytes")
        fitted = leaves if level == 0 else None
        array, table, k, at = fitted or fit_level(
            level_points, k, seed=seed + level, max_iter=max_iter, resample_rounds=resample_rounds, driver_bytes=driver_bytes
        )
        if level == 0:
            leaf_of = at.select("point_id", F.col("node").alias("c1"), "dist2")
            if array is not None and centroid_weight == "population":
                sizes = {r["c1"]: r["count"] for r in leaf_of.groupBy("c1").count().collect()}
                weight = np.array([sizes[i] for i in range(k)], float)
        else:
            up = at.select(F.col("point_id").alias("node"), F.col("node").alias("parent"))
            large[level - 1] = staged(large[level - 1].select("node", "centroid").join(up, "node").select("node", "parent", "centroid"))
            parents.append(None)
        if table is not None:
            large[level] = staged(table.select("node", F.lit(-1).cast("long").alias("parent"), "centroid"))
            level_points = large[level].select(F.col("node").alias("point_id"), F.col("centroid").alias("vec"))
        centroids.append(array)
        held.append(k)
        below = array
    return ClusterTree(centroids, parents, leaf_of, large, held)


__all__ = ["ClusterTree", "build_tree", "centroid_frame", "fit_level", "level_counts", "load_tree", "NARROW", "WIDE", "LEAST_TOP"]
