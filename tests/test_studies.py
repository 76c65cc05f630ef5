"""Budgets by volume, batches down the hierarchy, strict batches and the report on the grid."""

import random

import pytest
from pyspark.sql import functions as F

from evenset.operators import allocate, batching
from evenset.plans import methods, studies  # noqa: F401  (registers its queries)
from evenset.sources.tables import make_tiles

SF = "/root/testdata/sf0.001"


@pytest.mark.parametrize("budget", [0, 17, 400, 10**6])
def test_budget_by_volume(spark, budget):
    rng = random.Random(budget)
    rows = [(i, rng.randint(0, 40), rng.choice([0.0, 0.5, 1.0, rng.random() * 9])) for i in range(60)]
    got = allocate.allocate_by_volume(spark.createDataFrame(rows, "leaf int, size long, volume double"), budget).collect()
    assert len(got) == 60
    low, high = 0.0, 1e9
    for _ in range(200):  # the level by bisection
        mid = (low + high) / 2
        low, high = (mid, high) if sum(min(s, mid * v) for _, s, v in rows) < budget else (low, mid)
    for r in got:
        assert abs(r["granted"] - min(r["size"], int(high * r["volume"] + 1e-6))) <= (1 if high < 1e8 else 0) or high > 1e8
        assert 0 <= r["granted"] <= r["size"] and (r["volume"] > 0 or r["granted"] == 0)
    if budget == 10**6:
        assert all(r["granted"] == (r["size"] if r["volume"] > 0 else 0) for r in got)


def test_hierarchical_batches_are_even_at_both_levels(spark):
    rng = random.Random(5)
    rows = [(i, f"c{i % 5}", f"c{i % 5}:{rng.choice('abc')}") for i in range(400)]
    sub = spark.createDataFrame(rows, "point_id long, top string, low string")
    plan = batching.plan_hierarchical(sub, "top", "low", 20, 30).toPandas()
    assert (plan.groupby("iteration").size() == 20).all() and (plan.groupby(["iteration", "cluster"]).size() == 4).all()
    per = plan.groupby(["cluster", "child"]).size()
    for c, g in per.groupby(level=0):
        assert g.max() - g.min() <= 1
    for _, g in plan.sort_values(["iteration", "slot"]).groupby("child"):
        views = g.groupby("point_id").size()
        assert views.max() - views.min() <= 1 or len(views) < sum(r[2] == g["child"].iloc[0] for r in rows)
        assert views.max() == g["seen_before"].max() + 1


@pytest.mark.parametrize("batch,sizes", [(12, (10, 30)), (20, (500, 41)), (9, (4, 300))])
def test_strict_swaps_stay_near_the_ends_of_passes(spark, batch, sizes):
    rows = [(1000 * c + i, f"c{c}") for c, n in enumerate(sizes) for i in range(n)]
    sub = spark.createDataFrame(rows, "point_id long, c string")
    plain = batching.plan_stratified(sub, "c", batch, 40).toPandas()
    strict = batching.plan_stratified(sub, "c", batch, 40, strict=True).toPandas()
    small = min(sizes) < batch // 2 + 1  # then a cluster has to repeat
    assert len(strict) == len(plain) == 40 * batch
    assert small or not strict.duplicated(["iteration", "point_id"]).any()
    views = lambda p: p.groupby(["cluster", "point_id", "seen_before"]).size().to_dict()
    for c in set(plain["cluster"]):
        done = plain[plain.cluster == c]["seen_before"].max()  # whole passes hold the same tiles, however swapped
        whole = lambda p: p[(p.cluster == c) & (p.seen_before < done)]
        assert views(whole(strict)) == views(whole(plain))


def test_names_that_the_operators_use_inside(spark):
    pts = spark.range(200).select(F.col("id").alias("point_id"), (F.col("id") % 4).alias("g"))
    for name in ("granted", "size", "budget", "cap", "draw"):
        got = allocate.curate(pts.withColumn(name, F.lit("x")), ["g"], budget=40)
        assert got.count() == 40 and name in got.columns
    assert allocate.curate(pts.limit(0), ["g"], budget=5).count() == 0
    odd = allocate.curate(pts.withColumn("g", F.when(F.col("g") > 0, F.col("g"))), ["g"], budget=40)
    assert odd.where("g is not null").count() == 30


def test_tiles_cover_any_text(spark):
    rows = [(1, None), (2, ""), (3, "é" * 224), (4, "a\n" * 300), (5, "\U0001f600x" * 200), (6, "z" * 3_000_000)]
    docs = spark.createDataFrame(rows, "doc_id long, text string")
    tiles = make_tiles(docs).orderBy("tile_id").collect()
    for i, t in rows:
        mine = [r["content"] for r in tiles if r["slide_id"] == i]
        assert "".join(mine) == (t or "") and all(len(x) == 224 for x in mine[:-1])


def test_grid_report(spark):
    got = methods.Q["grid_report"](spark, SF).toPandas()
    assert set(got["measure"]) == {"mean", "place", "distance", "corr_distance", "corr_top_share", "corr_cohort_b"}
    assert got[got.measure == "place"]["value"].min() == 1 and got[got.measure == "distance"]["value"].between(0, 1).all()
    assert got[(got.measure == "mean") & (got.task == "overall")]["setting"].nunique() == 7
