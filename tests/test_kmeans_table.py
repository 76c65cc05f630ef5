"""Centroids as a table against centroids as an array."""

import numpy as np
import pytest
from pyspark.sql import functions as F

from evenset.functions.linalg import lloyd, nearest
from evenset.operators import kmeans, kmeans_table, metrics, tree

RNG = np.random.default_rng(3)
CENTRES = RNG.normal(size=(12, 8)) * 3
X = np.vstack([CENTRES[i % 12] + RNG.normal(size=8) * 0.4 for i in range(900)])


@pytest.fixture(scope="module")
def points(spark):
    rows = [(i, [float(v) for v in x]) for i, x in enumerate(X)]
    return spark.createDataFrame(rows, "point_id long, vec array<double>").repartition(5).cache()


def test_blocks_of_centroids_change_nothing():
    c = RNG.normal(size=(700, 8))
    at, d = nearest(X, c)
    few, e = nearest(X, c, most=6400)  # a hundred centroids at a time
    want = ((X[:, None, :] - c[None]) ** 2).sum(axis=2)
    assert (at == want.argmin(axis=1)).all() and (few == at).all() and np.allclose(d, e)


@pytest.mark.parametrize("per_task", [7, 8192])
def test_cells_assign_exactly(spark, points, per_task):
    c = X[RNG.permutation(len(X))[:90]]
    c[5] = c[6]  # a tie goes to the lower node
    table = kmeans.centroid_frame(spark, c)
    got = kmeans_table.assign_table(points, table, 90, per_task=per_task).toPandas().set_index("point_id").sort_index()
    at, d = nearest(X, c)
    assert (got["node"].to_numpy() == at).all() and np.allclose(got["dist2"], d)
    near = kmeans_table.assign_table(points, table, 90, nprobe=3).toPandas().set_index("point_id").sort_index()
    assert len(near) == len(X) and (near["node"].to_numpy() == at).mean() > 0.9


@pytest.mark.parametrize("empty", ["keep", "farthest"])
def test_steps_equal_plain_lloyd(points, empty):
    start = np.vstack([X[:30], np.full((2, 8), 99.0)])  # two clusters that never get a point
    plain = kmeans.kmeans_fit(points, 32, init=start, max_iter=4, tol=-1, empty=empty)
    large = kmeans.kmeans_fit(points, 32, init=start, max_iter=4, tol=-1, empty=empty, driver_bytes=0)
    assert plain.centroids is not None and large.centroids is None
    got = large.table.orderBy("node").toPandas()
    assert np.allclose(np.stack(got["centroid"]), plain.centroids) and np.allclose(large.history, plain.history)
    if empty == "keep":
        assert np.allclose(plain.centroids, lloyd(X, start, 4, tol=-1)[0])


@pytest.mark.parametrize("init", ["plusplus", "random"])
def test_seeds_as_a_table(points, init):
    large = kmeans.kmeans_fit(points, 40, init=init, max_iter=3, driver_bytes=0)
    random = kmeans.kmeans_fit(points, 40, init="random", max_iter=3)
    assert large.k == 40 and large.history == sorted(large.history, reverse=True)
    assert large.history[-1] <= (1.0 if init == "plusplus" else 1.0001) * random.history[-1] * 1.05
    assert kmeans_table.seed_grouped(points, 2000).count() <= len(X)


def invariants(t, n):
    sizes = [t.sizes(level + 1).agg(F.sum("n")).first()[0] for level in range(t.depth)]
    assert sizes == [n] * t.depth
    nodes = t.nodes().toPandas()
    assert nodes.groupby("level").size().tolist() == t.counts
    for level in range(1, t.depth):
        assert set(nodes[nodes.level == level].parent) == set(nodes[nodes.level == level + 1].node)
    kids = nodes[nodes.level > 1].groupby("level")["n_children"].sum().tolist()
    assert kids == t.counts[:-1]
    gaps = [metrics.mean_nn_distance(t.table(level)).first()[0] for level in range(t.depth)]
    assert gaps == sorted(gaps)  # centroids lie farther apart from level to level


@pytest.mark.parametrize("driver_bytes,large", [(1 << 28, 0), (64 * 12, 2)])
def test_tree_over_tables(spark, points, tmp_path, driver_bytes, large):
    t = tree.build_tree(points, [90, 24, 6], resample_rounds=int(not large), max_iter=2, driver_bytes=driver_bytes)
    assert sum(c is None for c in t.centroids) == large and len(t.counts) == 3
    invariants(t, len(X))
    assert t.paths().count() == len(X)
    leaf = t.route(points).join(t.leaf_of.withColumnRenamed("c1", "own").select("point_id", "own"), "point_id")
    assert leaf.where("c1 <> own").count() == 0
    greedy = t.route(points, "greedy")
    assert greedy.count() == len(X) and set(greedy.columns) == {"point_id", "c1", "dist2"}
    t.save(str(tmp_path / "t"))
    again = tree.load_tree(spark, str(tmp_path / "t"), driver_bytes)
    assert again.counts == t.counts and again.paths().exceptAll(t.paths()).count() == 0
    low = t.truncate(2)
    assert low.depth == 2 and set(low.paths().columns) == {"point_id", "c1", "c2"}
    if not large:
        sub = t.subtree(3, 0)
        held = t.paths().where("c3 = 0")
        assert sub.depth == 3 and sub.leaf_of.count() == held.count() and sub.counts[0] == held.select("c1").distinct().count()


def test_odd_points(spark, points):
    empty = points.limit(0)
    assert len(kmeans.kmeans_fit(empty, 3).centroids) == 0 and kmeans.assign(empty, np.zeros((0, 1))).count() == 0
    with pytest.raises(ValueError):
        tree.build_tree(empty, [3, 1])
    odd = spark.createDataFrame([(1, [0.0, 0.0]), (2, None), (3, [4.0, 4.0])], "point_id long, vec array<double>")
    m = kmeans.kmeans_fit(odd, 5)
    assert len(m.centroids) == 2 and m.assign(odd).count() == 2
    assert kmeans.kmeans_fit(odd, 5, driver_bytes=0).k == 2
