"""Worked examples, brute force and invariants of the curation methods."""

import random

import numpy as np
import pytest
from pyspark.sql import functions as F

from evenset.functions.linalg import lloyd, nearest, plusplus
from evenset.operators import allocate, batching, features, kmeans, learning, metrics, tree

SF = "/root/testdata/sf0.001"


def brute_cap(sizes, budget):
    return min(range(max([*sizes, 0]) + 1), key=lambda n: (abs(budget - sum(min(n, s) for s in sizes)), n))


@pytest.mark.parametrize("budget,cap", [(200, 92), (1115, 1000), (2000, 1000), (0, 0)])
def test_published_caps(budget, cap):
    assert allocate.fill_level_bisect([5, 10, 100, 1000], budget) == cap


def test_zero_trap():
    assert allocate.fill_level_bisect([20] * 5, 2) == 0


def test_closed_form_equals_bisection_and_brute(spark):
    rng = random.Random(1)
    rows, want = [], {}
    for p in range(200):
        sizes = [rng.randint(0, 30) for _ in range(rng.randint(1, 8))]
        budget = rng.randint(0, 150)
        rows += [(p, i, s, budget) for i, s in enumerate(sizes)]
        want[p] = brute_cap(sizes, budget)
        assert allocate.fill_level_bisect(sizes, budget) == want[p]
    df = spark.createDataFrame(rows, "p int, c int, size long, budget long")
    got = {r["p"]: r["cap"] for r in allocate.fill_levels(df, ["p"], "c").collect()}
    assert got == want


@pytest.mark.parametrize("budget", [0, 7, 60, 304, 1521, 10**6])
def test_exact_rounding_hits_the_budget(spark, budget):
    rng = random.Random(2)
    rows = [(i % 5, i % 37, i, rng.randint(1, 60)) for i in range(150)]
    leaves = spark.createDataFrame(rows, "a int, b int, c int, size long")
    out = allocate.allocate_tree(leaves, ["a", "b", "c"], budget, rounding="exact")["c"].toPandas()
    assert out["granted"].sum() == min(budget, sum(r[3] for r in rows))
    assert (out["granted"] <= out["size"]).all() and (out["granted"] >= 0).all()


def test_exhaust_budget_brute():
    sizes = [3, 5, 5, 9]
    for s, b in zip(sizes, allocate.exhaust_budget(sizes)):
        assert brute_cap(sizes, b) >= s and brute_cap(sizes, b - 1) < s


def test_draw_does_not_depend_on_partitions(spark):
    df = spark.range(3000).select(F.col("id").alias("point_id"), (F.col("id") % 7).alias("g"))
    a = {r["point_id"] for r in allocate.curate(df.repartition(1), ["g"], budget=100).collect()}
    b = {r["point_id"] for r in allocate.curate(df.repartition(13), ["g"], budget=100).collect()}
    assert a == b and len(a) == 98


def test_tv_examples(spark):
    c = spark.createDataFrame([("a", 4)], "k string, n long")
    u = spark.createDataFrame([("a",), ("b",), ("c",), ("d",)], "k string")
    assert metrics.tv_uniform(c, u, ["k"]).first()["tv"] == pytest.approx(0.75)


def test_agreement_examples(spark):
    df = spark.createDataFrame([(0, "x", 0), (0, "x", 0), (1, "y", 0), (1, "y", 0)], "a int, b string, one int")
    assert metrics.adjusted_rand(df, "a", "b").first()["ari"] == 1.0
    assert metrics.adjusted_rand(df, "one", "b").first()["ari"] == 0.0
    assert metrics.balanced_accuracy(df.withColumn("p", F.lit(0)), "a", "p").first()["bacc"] == 0.5
    tied = df.select(F.col("a").alias("y"), F.lit(1.0).alias("s"))
    assert metrics.roc_auc(tied, "y", "s").first()["auc"] == 0.5


@pytest.mark.parametrize("batch,k", [(32, 7), (32, 32), (16, 5), (5, 7)])
def test_stratified_plan(spark, batch, k):
    rng = random.Random(batch * k)
    rows, n = [], 0
    for c in range(k):
        for _ in range(rng.choice([1, 3, 20])):
            rows.append((n, f"c{c:02d}"))
            n += 1
    sub = spark.createDataFrame(rows, "point_id long, c string")
    plan = batching.plan_stratified(sub, "c", batch, 24).toPandas()
    assert (plan.groupby("iteration").size() == batch).all() and plan["iteration"].nunique() == 24
    per = plan.groupby(["iteration", "cluster"]).size()
    assert per.max() <= batch // k + 1
    total = plan.groupby("cluster").size()
    assert total.max() - total.min() <= 1
    for _, g in plan.sort_values(["iteration", "slot"]).groupby("cluster"):
        size = sum(1 for r in rows if r[1] == g["cluster"].iloc[0])
        seen = dict.fromkeys((r[0] for r in rows if r[1] == g["cluster"].iloc[0]), 0)
        for i, p in enumerate(g["point_id"]):
            seen[p] += 1
            assert max(seen.values()) - min(seen.values()) <= 1
        assert len(seen) == size
    tv = batching.batch_tv(batching.plan_stratified(sub, "c", batch, 24), k).first()
    r = batch % k
    assert tv["max_tv"] == pytest.approx(r * (k - r) / (k * batch))


def test_strict_plan_has_no_repeats(spark):
    sub = spark.range(40).select(F.col("id").alias("point_id"), F.when(F.col("id") < 10, "a").otherwise("b").alias("c"))
    plan = batching.plan_stratified(sub, "c", 12, 30, strict=True).toPandas()
    assert not plan.duplicated(["iteration", "point_id"]).any() and len(plan) == 360


def test_shuffled_epochs_are_permutations(spark):
    sub = spark.range(50).withColumnRenamed("id", "point_id")
    plan = batching.plan_shuffled(sub, 10, 15).toPandas().sort_values(["iteration", "slot"])
    ids = plan["point_id"].tolist()
    assert len(ids) == 150 and all(sorted(ids[i : i + 50]) == list(range(50)) for i in (0, 50, 100))
    assert batching.plan_shuffled(sub, 8, 5, mode="replace").count() == 40


def points(spark, n=400, d=5, seed=0):
    x = np.random.default_rng(seed).normal(size=(n, d)) + np.arange(n)[:, None] % 4 * 3
    return x, spark.createDataFrame([(i, [float(v) for v in r]) for i, r in enumerate(x)], "point_id long, vec array<double>")


def test_assignment_strategies_agree(spark):
    x, df = points(spark)
    c = x[:30]
    want = dict(zip(range(len(x)), nearest(x, c)[0].tolist()))
    for s in ("expr", "broadcast_gemm", "blocked"):
        assert {r["point_id"]: r["node"] for r in kmeans.assign(df, c, strategy=s).collect()} == want
    coarse = {r["point_id"]: r["node"] for r in kmeans.assign(df, c, strategy="coarse", nprobe=4).collect()}
    assert sum(coarse[i] == want[i] for i in want) >= 0.95 * len(want)


def test_neighbours_of_every_hundredth_row(spark):
    import __spark_entry__ as e

    rows = spark.read.parquet(f"{SF}/embeddings.parquet").orderBy("vec_id").collect()
    ids, x = np.array([r["vec_id"] for r in rows]), np.array([r["embedding"] for r in rows], float)
    want = set()
    for i in np.flatnonzero(ids % 100 == 0):
        order = np.lexsort((ids, ((x - x[i]) ** 2).sum(1)))
        want |= {(int(ids[i]), int(j)) for j in ids[order[order != i][:5]]}
    got = e.queries()["retrieve_neighbours_hundredths"](spark, SF).collect()
    assert len(got) == len(want) == 5 * int((ids % 100 == 0).sum()) and {tuple(r) for r in got} == want
    p = spark.createDataFrame([(int(i), [float(a) for a in v]) for i, v in zip(ids, x)], "point_id long, vec array<double>")
    small = kmeans.block_neighbours(p, p.where("point_id % 100 = 0"), 5, query_block=2, row_block=60)
    assert {(r["seed"], r["point_id"]) for r in small.collect()} == want


def test_inertia_never_rises(spark):
    _, df = points(spark)
    for init in ("plusplus", "parallel", "random"):
        h = kmeans.kmeans_fit(df, 8, init=init, max_iter=8).history
        assert all(b <= a * (1 + 1e-9) for a, b in zip(h, h[1:]))


def test_tree_invariants(spark, tmp_path):
    x, df = points(spark)
    t = tree.build_tree(df, [40, 12, 4], resample_rounds=1)
    paths = t.paths().toPandas()
    assert len(paths) == len(x) and paths.notna().all().all()
    assert t.sizes(3).agg(F.sum("n")).first()[0] == len(x)
    assert set(t.parent[0]) == set(range(len(t.centroids[1])))
    t.save(str(tmp_path / "tree"))
    assert tree.load_tree(spark, str(tmp_path / "tree")).paths().count() == len(x)
    assert t.route(df, "greedy").count() == len(x)
    near = lambda c: np.sqrt(np.partition(((c[:, None] - c[None]) ** 2).sum(-1), 1, axis=1)[:, 1]).mean()
    assert near(t.centroids[0]) <= near(t.centroids[1])


def test_level_counts():
    assert tree.level_counts(350_000_000, shape="narrow") == [3_500_000, 35_000, 350, 62]
    assert tree.level_counts(350_000_000, shape="wide") == [3_500_000, 100_000, 10_000, 2048]


@pytest.mark.parametrize("shape,top", [("narrow", 7), ("wide", 32)])
def test_level_counts_grow_with_the_points(shape, top):
    for n in (11_254, 115_693, 2_000_000, 40_000_000, 350_000_000):
        got = tree.level_counts(n, shape=shape)
        assert got[0] == round(n / 100) and got[-1] >= top and got == sorted(set(got), reverse=True)
    assert tree.level_counts(2266, shape=shape)[-1] == min(top, 11) and tree.level_counts(0, shape=shape) == [1] * 4


def test_tree_sizes_do_not_follow_the_folder_name(spark, tmp_path):
    from evenset.plans import methods

    other = tmp_path / "any_name"
    other.mkdir()
    docs = spark.read.parquet(f"{SF}/documents.parquet")
    docs.write.parquet(str(other / "documents.parquet"))
    n = methods.tile_points(spark, SF).count()
    for sf in (SF, str(other)):
        t = methods.built(spark, sf, "narrow")
        want = tree.level_counts(n, shape="narrow")
        assert all(0 < len(c) <= k for c, k in zip(t.centroids, want)) and len(t.centroids[0]) >= 0.8 * n / 100


def test_both_trees_share_one_fit_of_their_leaves(spark, monkeypatch):
    from evenset.plans import methods

    fits, plain = [], tree.kmeans_fit
    monkeypatch.setattr(tree, "kmeans_fit", lambda points, k, **how: (fits.append(k), plain(points, k, **how))[1])
    assert methods.Q["balance_curve_trees"](spark, SF).count() > 0
    assert len(fits) == 1
    for shape, t in methods.both_built(spark, SF):
        alone = methods.built(spark, SF, shape)
        assert t.counts == alone.counts and all(np.allclose(a, b) for a, b in zip(t.centroids, alone.centroids))
        assert all((a == b).all() for a, b in zip(t.parent, alone.parent))
        assert sorted(map(tuple, t.leaf_of.select("point_id", "c1").collect())) == sorted(map(tuple, alone.leaf_of.select("point_id", "c1").collect()))


def test_embedding_forms_agree(spark):
    from evenset.sources.tables import make_tiles, table

    tiles = make_tiles(table(spark, SF, "documents")).where("slide_id < 20")
    cells = features.bigram_cells(tiles).toPandas()
    for r in features.hash_embed(tiles).collect():
        v = np.zeros(64)
        mine = cells[cells["tile_id"] == r["point_id"]]
        v[mine["bucket"]] = mine["n"]
        assert np.allclose(r["vec"], v / (np.linalg.norm(v) or 1))


def test_attention_gradient():
    rng = np.random.default_rng(0)
    bag, p = rng.normal(size=(5, 4)), [rng.normal(size=(4, 3)), rng.normal(size=3), rng.normal(size=4), 0.3]
    loss = lambda q: -np.log(learning.mil_forward(q, bag)[0])
    g = learning.mil_gradient(p, bag, 1.0)
    for i in range(3):
        flat = p[i].reshape(-1)
        for j in range(flat.size):
            up = [a.copy() if hasattr(a, "copy") else a for a in p]
            down = [a.copy() if hasattr(a, "copy") else a for a in p]
            up[i].reshape(-1)[j] += 1e-6
            down[i].reshape(-1)[j] -= 1e-6
            assert g[i].reshape(-1)[j] == pytest.approx((loss(up) - loss(down)) / 2e-6, abs=1e-5)


def test_flagship_and_registry(spark):
    import __spark_entry__ as e

    found, sql = e.queries(), e.oracle_sql()
    assert set(sql) <= set(found) and len(found) > 100
    assert e.entry(spark).count() > 0
