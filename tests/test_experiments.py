"""Measures, seeding, plans and experiment grids against brute force."""

import hashlib

import numpy as np
import pandas as pd
from pyspark.sql import functions as F

from evenset.functions.linalg import nearest, to_matrix
from evenset.operators import allocate, batching, kmeans, metrics
from evenset.plans import experiments, extras

SF = "/root/testdata/sf0.001"


def brute_auc(y, s):
    p, q = s[y == 1], s[y == 0]
    return (p[:, None] > q[None]).mean() + (p[:, None] == q[None]).mean() / 2


def test_auc_by_range_partitions_and_by_groups(spark):
    rng = np.random.default_rng(3)
    pdf = pd.DataFrame({"g": rng.integers(0, 3, 900), "y": rng.integers(0, 2, 900), "s": rng.integers(0, 60, 900) / 64.0})
    df = spark.createDataFrame(pdf)
    assert abs(metrics.roc_auc(df, "y", "s").first()[0] - brute_auc(pdf.y.to_numpy(), pdf.s.to_numpy())) < 1e-12
    for row in metrics.roc_auc_by(df, "y", "s", ["g"], digits=9).collect():
        part = pdf[pdf.g == row["g"]]
        assert abs(row["auc"] - brute_auc(part.y.to_numpy(), part.s.to_numpy())) < 1e-12


def test_auc_of_one_class_is_null(spark):
    df = spark.createDataFrame([("a", 1, 0.5), ("a", 1, 0.7)], "g string, y int, s double")
    assert metrics.roc_auc_by(df, "y", "s", ["g"]).first()["auc"] is None


def test_sum_before_and_ordinals(spark):
    df = spark.range(1000).select("id", (F.col("id") % 7).alias("v"), F.md5(F.col("id").cast("string").cast("binary")).alias("k"))
    got = batching.sum_before(df, [F.col("k")], "v").toPandas().sort_values("k")
    assert (got["before"].to_numpy() == np.concatenate([[0], got["v"].cumsum().to_numpy()[:-1]])).all()
    got = batching.global_ordinal(df, [F.col("k")]).toPandas().sort_values("k")
    assert (got["ordinal"].to_numpy() == np.arange(1000)).all()
    assert batching.global_ordinal(df.limit(0), [F.col("k")]).count() == 0


def test_seeds_are_points_and_farthest_is_greedy(spark):
    x = np.random.default_rng(1).normal(size=(120, 3))
    pts = spark.createDataFrame([(i, [float(a) for a in v]) for i, v in enumerate(x)], "point_id long, vec array<double>")
    ids, vecs = kmeans.seed_passes(pts, 6, how="farthest")
    d = ((x - x[ids[0]]) ** 2).sum(1)
    for i in ids[1:]:
        assert i == int(d.argmax())
        d = np.minimum(d, ((x - x[i]) ** 2).sum(1))
    ids, vecs = kmeans.seed_passes(pts, 6)
    assert len(set(ids)) == 6 and np.allclose(vecs, x[ids])
    same = spark.createDataFrame([(i, [1.0]) for i in range(4)], "point_id long, vec array<double>")
    assert len(kmeans.seed_passes(same, 3)[0]) == 1  # copies only: one seed


def test_oversampled_seeds_are_distinct_points_and_cover_blobs(spark):
    rng = np.random.default_rng(3)
    centres = rng.normal(0, 50, (12, 4))
    x = np.repeat(centres, 40, axis=0) + rng.normal(0, 0.1, (480, 4))
    points = spark.createDataFrame([(i, v.tolist()) for i, v in enumerate(x)], "point_id long, vec array<double>")
    seeds = kmeans.seed_parallel(points, 12, seed=5)
    assert seeds.shape == (12, 4) and len(np.unique(seeds, axis=0)) == 12
    assert all((np.abs(x - s).sum(axis=1) < 1e-12).any() for s in seeds)
    assert set(nearest(seeds, centres)[0]) == set(range(12))  # one seed a blob
    assert np.array_equal(seeds, kmeans.seed_parallel(points.repartition(5), 12, seed=5))


def test_race_draws_in_proportion_to_distance(spark):
    pts = spark.createDataFrame([(0, [0.0]), (1, [1.0]), (2, [3.0])], "point_id long, vec array<double>").cache()
    hits = [kmeans.seed_passes(pts, 2, seed=s)[0] for s in range(25)]
    assert all(len(set(h)) == 2 for h in hits) and len({tuple(h) for h in hits}) > 2


def test_spread_takes_one_row_per_draw_and_node(spark):
    rows = [(i, i % 2, [float(i), 0.0], float(i)) for i in range(20)]
    a = spark.createDataFrame(rows, "point_id long, node long, vec array<double>, dist2 double")
    got = allocate.draw_by_distance(a, 3, "spread").toPandas()
    assert sorted(got[got.node == 0].point_id) == [0, 8, 18]  # 8 and 10 tie
    few = a.where("point_id < 2")
    assert allocate.draw_by_distance(few, 3, "spread").count() == 2  # nodes of one point give that point


def test_plan_source_is_even_and_least_seen_first(spark):
    spark.dataSource.register(extras.PlanSource)
    p = spark.read.format("evenset_plan").options(sizes="3,50,7", batch=10, iterations=21, parts=4).load().toPandas()
    assert (p.groupby("iteration").size() == 10).all()
    per = p.groupby(["iteration", "cluster_no"]).size()
    assert per.min() == 3 and per.max() == 4
    for _, g in p.groupby("cluster_no"):
        views = g.groupby("place").size()
        assert views.max() - views.min() <= 1 or len(views) < g["place"].max() + 1


def test_bootstrap_of_cells(spark):
    cells = spark.createDataFrame([("s", "t", "a", "a", 80), ("s", "t", "a", "b", 20), ("s", "t", "b", "b", 60), ("s", "t", "b", "a", 40)], "setting string, task string, truth string, pred string, n long")
    row = metrics.bootstrap_cells(cells, ["setting", "task"]).first()
    assert abs(row["mean"] - 0.7) < 0.01 and 0.02 < row["std"] < 0.05 and row["tested"] == 200


def test_region_tasks_cover_all_items_and_split_whole_units(spark):
    items = experiments.region_items(spark, SF).select("item_id", "unit", "held_out", F.map_keys("labels").alias("t")).toPandas()
    assert items["item_id"].is_unique
    assert items.groupby("unit")["held_out"].nunique().max() == 1
    assert {x for t in items["t"] for x in t} == {"r1_points", "r2_language", "r3_source", "r4_cohort", "r5_role", "r6_page_language", "r7_quality", "r8_benchmark"}


def test_training_takes_one_pass_of_the_pool(spark):
    from evenset.plans.methods import tile_paths

    sf = "/root/testdata/sf0.01"
    pool = tile_paths(spark, sf).withColumn("c", F.col("lang"))
    small = pool.where("pmod(xxhash64(point_id), 10) = 0")
    n, length = pool.count(), experiments.pool_iterations(spark, sf)
    assert length == -(-n // 32) == 352
    full = experiments.plan_for("full", pool, None, length).toPandas()
    assert len(full) == 32 * length and full["point_id"].nunique() == n
    for cluster in (None, "c"):
        few = experiments.plan_for("few", small, cluster, length).toPandas()
        assert len(few) == 32 * length and few["point_id"].nunique() == small.count()


def test_learner_folds_over_chunks(spark):
    rng = np.random.default_rng(8)
    x = rng.normal(size=(90, 64))
    vecs = spark.createDataFrame([(i, [float(a) for a in v]) for i, v in enumerate(x)], "point_id long, vec array<double>")
    picks = {name: rng.integers(0, 90, (25, 6)) for name in "abc"}
    rows = [(s, t, j, int(p)) for s, plan in picks.items() for t, b in enumerate(plan) for j, p in enumerate(b)]
    plans = spark.createDataFrame(rows, "setting string, iteration long, slot int, point_id long").repartition(5)
    size = "spark.sql.execution.arrow.maxRecordsPerBatch"
    spark.conf.set(size, "7")
    try:
        got = experiments.learn_settings(plans, vecs)
    finally:
        spark.conf.unset(size)
    assert set(got) == set(picks)
    for name, plan in picks.items():
        assert np.allclose(got[name], experiments.learning.oja([x[b] for b in plan], 64))


def test_benchmark_overlap_matches_brute_force(spark):
    from evenset.plans.methods import doc_tiles

    def grams(t):
        w = t.lower().split()
        return {tuple(w[i : i + 8]) for i in range(len(w) - 7)}

    known = set()
    for x in spark.read.parquet(f"{SF}/benchmark.parquet").collect():
        known |= grams(x["text"])
    want = {x["tile_id"] for x in doc_tiles(spark, SF).collect() if grams(x["content"]) & known}
    assert {x[0] for x in experiments.overlaps_benchmark(spark, SF).collect()} == want


def test_slide_tasks_score_every_held_out_bag(spark):
    bags = experiments.slide_bags(spark, SF)
    n = bags.count()
    assert n == spark.read.parquet(f"{SF}/documents.parquet").where("length(text) > 0").count()
    got = experiments.slide_grid(bags, runs=3, train_bags=30).toPandas()
    assert len(got) == 27 and set(got["model"]) == {"attention", "mean", "max"}
    english = got[(got.task == "english_1") & (got.model == "mean")]["mean"].iloc[0]
    assert english > 0.8


def test_learner_gets_points_once_or_with_each_draw(spark, monkeypatch):
    tiles = spark.createDataFrame([(i, f"some tile {i * i} of text {i % 7}" * (1 + i % 4)) for i in range(90)], "tile_id long, content string")
    packed = experiments.features.packed_embed(tiles)
    vec = {x["point_id"]: x["vec"] for x in experiments.features.hash_embed(tiles).collect()}
    rng = np.random.default_rng(4)
    picks = {"few": rng.integers(0, 5, (40, 6)), "many": rng.integers(0, 90, (40, 6)), "other": rng.integers(20, 50, (3, 6))}
    rows = [(s, t, j, int(p)) for s, plan in picks.items() for t, b in enumerate(plan) for j, p in enumerate(b)]
    rows.append(("few", 0, 6, 12345))  # has no vector
    plans = spark.createDataFrame(rows, "setting string, iteration long, slot int, point_id long").repartition(5)
    spark.conf.set("spark.sql.execution.arrow.maxRecordsPerBatch", "7")
    try:
        ways = [experiments.learn_settings(plans, packed, held) for held in (1000, 40, 0)]
    finally:
        spark.conf.unset("spark.sql.execution.arrow.maxRecordsPerBatch")
    for got in ways:
        for name, plan in picks.items():
            want = experiments.learning.oja([np.array([vec[p] for p in b]) for b in plan], 64)
            assert np.allclose(got[name], want, atol=1e-12)


def test_probes_are_fit_on_all_items_in_both_ways(spark):
    rng = np.random.default_rng(6)
    ids = sorted((f"i{i}" for i in range(4000)), key=lambda i: hashlib.md5(f"7:{i}".encode()).hexdigest())
    kind = rng.choice(["a", "b"], 4000).astype(object)
    kind[-60:] = "rare"  # behind the first 3,000 of each order by priority
    x = rng.normal(size=(4000, 6)) + 4.0 * np.array([{"a": [1, 0, 0, 0, 0, 0], "b": [0, 1, 0, 0, 0, 0], "rare": [0, 0, 1, 1, 0, 0]}[k] for k in kind])
    labels = [{"kind": str(k)} | ({"few": "yes" if v[4] > 0 else "no"} if i % 9 == 0 else {}) for i, (k, v) in enumerate(zip(kind, x))]
    rows = [(f"{h}{i}", v.tolist(), a, h == "h") for i, v, a in zip(ids, x, labels) for h in ("", "h")]
    items = spark.createDataFrame(rows, "item_id string, vec array<double>, labels map<string,string>, held_out boolean").repartition(3)
    models = {"all": np.eye(6), "turned": np.linalg.qr(rng.normal(size=(6, 6)))[0]}
    classes = {"few": ["no", "yes"], "kind": ["a", "b", "rare"]}
    few = np.arange(0, 4000, 9)
    got = experiments.run_grid(models, items, reps=50).toPandas().set_index(["setting", "task"])["mean"]
    assert len(got) == 4 and got.loc["all", "kind"] > 0.95 and got.loc["turned", "kind"] > 0.95
    train = items.where("not held_out").withColumnRenamed("item_id", "point_id")
    for held in (1 << 20, 0):
        fitted = experiments.probes.fit_probes(train, models, classes, held)
        for name, w in models.items():
            y = np.array([classes["kind"].index(k) for k in kind])
            assert np.allclose(fitted[name, "kind"], experiments.learning.fit_probe(x @ w, y, 3), atol=1e-9)
            y = (x[few, 4] > 0).astype(int)
            assert np.allclose(fitted[name, "few"], experiments.learning.fit_probe(x[few] @ w, y, 2), atol=1e-9)


def test_subsets_of_several_fractions_in_one_pass(spark):
    from evenset.plans.methods import tile_paths

    pool = tile_paths(spark, SF).select("point_id", "lang", "ls", "slide_id")
    levels = ["lang", "ls", "slide_id"]
    got = allocate.curate_percents(pool, levels, (1, 20, 50)).select("run", "point_id").collect()
    for percent in (1, 20, 50):
        want = {x["point_id"] for x in allocate.curate(pool, levels, fraction=percent / 100).collect()}
        mine = [x["point_id"] for x in got if x["run"] == percent]
        assert len(mine) == len(want) and set(mine) == want and (want or percent == 1)
