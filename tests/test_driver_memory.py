"""What reaches the driver when trees are built: matrices by way of Arrow, seeds of many clusters drawn in tasks."""

import numpy as np
import pytest
from pyspark.sql import functions as F

from evenset.functions import linalg
from evenset.functions.linalg import collect_matrix, matrix_frame, nearest, priority
from evenset.operators import features, kmeans, projection, tree
from evenset.plans import methods


def cloud(spark, n, dim=4):
    x = np.random.default_rng(n).normal(size=(n, dim))
    return x, matrix_frame(spark, {"point_id": np.arange(n)}, "vec", x)


def test_matrices_come_back_as_they_went(spark):
    x, df = cloud(spark, 300)
    rows, got = collect_matrix(df.orderBy("point_id"), "vec")
    assert (got == x).all() and rows.column("point_id").to_pylist() == list(range(300))
    assert collect_matrix(df.limit(0), "vec")[1].shape == (0, 1)
    assert matrix_frame(spark, {"node": np.arange(0)}, "centroid", x[:0]).count() == 0


@pytest.mark.parametrize("rows", [1, 50, 2999, 3000, 9000])
def test_sample_is_that_of_least_priority(spark, rows):
    x, df = cloud(spark, 3000)
    order = [r["point_id"] for r in df.orderBy(priority(3, F.col("point_id")), "point_id").select("point_id").limit(rows).collect()]
    assert (kmeans.priority_sample(df.repartition(7), rows, 3) == x[order]).all()


def test_many_seeds_are_not_drawn_from_a_sample_on_the_driver(spark, monkeypatch):
    x, df = cloud(spark, 600)
    seen, plain = [], kmeans.priority_sample
    monkeypatch.setattr(kmeans, "priority_sample", lambda p, rows, seed: (seen.append(rows), plain(p, rows, seed))[1])
    seeds = kmeans.seed_plusplus(df, 100, sample_rows=200)
    assert max(seen) < 100 and len(seeds) == 100 and len(np.unique(seeds, axis=0)) == 100
    assert (nearest(seeds, x)[1] < 1e-20).all()  # rows of the table
    few = kmeans.plusplus(plain(df, 200, 1), 40, np.random.default_rng(1))
    assert (kmeans.seed_plusplus(df, 40, sample_rows=200) == few).all()


def test_nearest_in_tiles_of_pairs():
    rng = np.random.default_rng(2)
    x, c = rng.normal(size=(1100, 3)), rng.normal(size=(5000, 3))
    c[4000:4010] = c[10:20]  # equal centroids in two tiles: the lower index wins
    d = ((x[:, None] - c[None]) ** 2).sum(-1)
    at, best = nearest(x, c)
    assert np.allclose(best, d.min(1)) and (at[np.isin(d.argmin(1), range(10, 20))] < 20).all()


def test_levels_pass_the_driver_as_arrow(spark, monkeypatch):
    x, df = cloud(spark, 400)
    made, plain = [], type(spark).createDataFrame
    monkeypatch.setattr(type(spark), "createDataFrame", lambda self, data, *a, **b: (made.append(data), plain(self, data, *a, **b))[1])
    t = tree.build_tree(df, [30, 6], max_iter=2)
    made.clear()
    assert t.nodes().where("level = 1").count() == t.counts[0]
    assert not any(isinstance(rows, list) for rows in made)


@pytest.mark.parametrize("shift", [0.0, 300.0])
def test_single_precision_only_screens(spark, shift):
    rng = np.random.default_rng(5)
    x, c = rng.normal(size=(700, 6)) + shift, rng.normal(size=(linalg.SCREENED + 77, 6)) + shift
    c[1500:1510], x[:50] = c[20:30], c[15:65]  # equal centroids in two tiles, and points on centroids
    c[40] = c[41] + 1e-6  # nearer to each other than single precision can tell
    d = np.stack([((row - c) ** 2).sum(axis=1) for row in x])
    found = linalg._screened(x, c, 256)
    assert (found[0] == d.argmin(axis=1)).all() and (found[1] == d.min(axis=1)).all()
    assert (nearest(x, c)[0] == found[0]).all()
    assert linalg._screened(x, c * 1e16, 256) is None  # beyond the error bound: double precision throughout


def test_tiles_are_ruled_out_only_by_true_bounds():
    rng = np.random.default_rng(7)
    middles = rng.normal(0, 3, (40, 12))
    c = np.repeat(middles, 100, axis=0) + rng.normal(0, 0.3, (4000, 12))
    x = np.vstack([np.repeat(middles, 20, axis=0) + rng.normal(0, 0.3, (800, 12)), rng.normal(0, 3, (60, 12)), c[:40]])
    c[3000:3010] = c[10:20]  # equal centroids: the lower index
    d = np.stack([((row - c) ** 2).sum(axis=1) for row in x])
    known = linalg.screen(c)
    for at, near in (nearest(x, c), nearest(x, c, known=known), nearest(x, c, block=100, known=known)):
        assert (at == d.argmin(axis=1)).all() and (near == d.min(axis=1)).all()
    y = x - known.middle
    far = np.sqrt((y**2).sum(axis=1))
    bound = known._bounds(y, far, np.zeros(len(x)))[0].astype(float)
    least = np.stack([d[:, t].min(axis=1) for t in known.tiles]) - far**2
    assert sorted(np.concatenate(known.tiles)) == list(range(4000)) and (bound <= least).all()
    assert (bound <= d.min(axis=1) - far**2).mean() < 0.3  # the others are not visited


def test_a_step_leaves_no_centroids_behind(spark, monkeypatch):
    x, df = cloud(spark, 300)
    sent, plain = [], type(spark.sparkContext).broadcast
    monkeypatch.setattr(type(spark.sparkContext), "broadcast", lambda self, v: (sent.append(plain(self, v)), sent[-1])[1])
    c = kmeans.kmeans_fit(df, 12, init=x[:12].copy(), max_iter=4, tol=-1).centroids
    assert len(sent) == 4 and not any(b._jbroadcast.isValid() for b in sent)
    assert np.allclose(c, linalg.lloyd(x, x[:12], 4, tol=-1)[0])


def test_listing_a_tree_sends_no_centroids(spark, monkeypatch):
    made, plain = [], type(spark).createDataFrame
    monkeypatch.setattr(type(spark), "createDataFrame", lambda self, data, *a, **b: (made.append(data), plain(self, data, *a, **b))[1])
    rows = methods.Q["tree_full_narrow"](spark, "/root/testdata/sf0.001")
    assert rows.columns == ["level", "node", "parent", "n_children"] and rows.where("level = 1").count() > 10
    assert made and not any("centroid" in getattr(t, "column_names", []) for t in made)


def test_packed_vectors_are_equal_and_small(spark, tmp_path):
    texts = ["", "a", "Abba abba", None, "é😀x" * 30, "\n" * 224] + [f"tile number {i} of some" * 9 for i in range(400)]
    tiles = spark.createDataFrame(list(enumerate(texts)), "tile_id int, content string")
    plain = features.hash_embed(tiles)
    packed = features.packed_embed(tiles)
    got, want = ({r["point_id"]: r["vec"] for r in df.collect()} for df in (features.unpacked(packed), plain))
    assert got == want
    sizes = []
    for name, df in (("packed", packed), ("plain", plain)):
        df.coalesce(1).write.option("compression", "none").option("parquet.enable.dictionary", "false").parquet(f"{tmp_path}/{name}")
        sizes.append(sum(p.stat().st_size for p in (tmp_path / name).glob("*.parquet")))
    assert sizes[0] < 0.6 * sizes[1]


def test_landmarks_are_not_collected_as_rows(spark, monkeypatch):
    x, df = cloud(spark, 500)
    near = projection.neighbour_layout(df, landmarks=60, epochs=5)
    monkeypatch.setattr(type(df), "collect", lambda self: pytest.fail("rows of Python floats"))
    again = projection.neighbour_layout(df, landmarks=60, epochs=5)
    monkeypatch.undo()
    assert sorted(near.collect()) == sorted(again.collect()) and near.count() == 500
