"""Budget mixing and packing against plain reference computations."""

import random

import pandas as pd
import pytest
from pyspark.sql import functions as F

from evenset.llm import budget_mix, packing
from evenset.llm.budget_mix import bounded_subset, fit_budget, mix_documents, op2_budget_mix, plan_mix
from evenset.llm.packing import pack_documents, pack_shard

SF = "/root/testdata/sf0.01"
SCHEMA = "doc_id long, text string, source string"


def reshared(sizes: dict, share=1.5, repeats=2.0, weights=(3, 1, 2)) -> dict:
    """Targets by handing out the budget again and again until nothing is above its limit."""
    names = sorted(sizes)
    w = {n: weights[i % 3] for i, n in enumerate(names)}
    fixed: dict = {}
    while True:
        open_names = [n for n in names if n not in fixed]
        left = share * sum(sizes.values()) - sum(fixed.values())
        goal = {n: left * w[n] / sum(w[m] for m in open_names) for n in open_names}
        over = [n for n in open_names if goal[n] > repeats * sizes[n]]
        if not over:
            return fixed | goal
        fixed |= {n: repeats * sizes[n] for n in over}


def test_bounded_subset_is_best():
    rng = random.Random(1)
    for _ in range(300):
        lengths = rng.sample(range(1, 30), rng.randint(1, 5))
        counts = [rng.randint(0, 4) for _ in lengths]
        budget = rng.randint(0, 80)
        sums = {0}
        for size, n in zip(lengths, counts):
            sums = {s + k * size for s in sums for k in range(n + 1)}
        take = bounded_subset(lengths, counts, budget)
        assert all(0 <= t <= n for t, n in zip(take, counts))
        assert sum(a * b for a, b in zip(lengths, take)) == max(s for s in sums if s <= budget)
        take = fit_budget(lengths, counts, budget, slack=10)
        got = sum(a * b for a, b in zip(lengths, take))
        assert got <= budget and all(0 <= t <= n for t, n in zip(take, counts))


def test_targets_and_taken(spark):
    rows = op2_budget_mix(spark, SF).toPandas()
    docs = spark.read.parquet(f"{SF}/documents.parquet").select("doc_id", "source", "text").toPandas()
    docs["n"] = [len(t.encode().split()) for t in docs["text"]]
    both = rows.merge(docs, on="doc_id")
    assert len(both) == len(docs) and (both["size"] == both["n"]).all()
    goal = reshared(docs.groupby("source")["n"].sum().to_dict())
    assert both["target"].sub(both["source"].map(goal)).abs().max() < 1e-6
    per = both.groupby("source").agg(taken=("taken", "sum"), target=("target", "first"))
    # sources of 50 documents cannot always hit a number exactly
    assert ((per["taken"] - per["target"]).abs() <= 0.001 * per["target"]).all()
    assert (both["taken"] <= 2 * both["size"]).all()
    again = op2_budget_mix(spark, SF).toPandas()
    assert dict(zip(rows["doc_id"], rows["taken"])) == dict(zip(again["doc_id"], again["taken"]))


def test_mix_corner_rows(spark):
    rows = [(1, None, "a"), (2, "", None), (None, "x y z", None), (3, "one two", "a"), (3, "one two", "a"), (4, "w " * 50, "b")]
    docs = spark.createDataFrame(rows, SCHEMA).withColumn("size", F.lit("clash")).withColumn("copies", F.lit(9))
    out = mix_documents(docs)
    assert out.columns == docs.columns
    plan = plan_mix(docs).toPandas()
    assert len(plan) == 6 and plan["copies"].between(0, 2).all()
    assert out.count() == plan["copies"].sum()
    assert mix_documents(docs.limit(0)).count() == 0


def test_mix_takes_its_options(spark):
    docs = spark.createDataFrame([(i, "w " * 10, "ab"[i % 2]) for i in range(20)], "no long, words string, kind string")
    docs = docs.withColumn("__size", F.lit(1)).withColumn("row", F.lit("x")).withColumn("copies", F.lit(5))
    options = {"id_col": "no", "text_col": "words", "source_col": "kind", "weights": (1, 1), "budget_share": 3.0, "max_repeats": 3.0}
    out = mix_documents(docs, **options)
    assert out.columns == docs.columns and out.count() == 60
    assert {r["count"] for r in out.groupBy("no").count().collect()} == {3}
    uneven = plan_mix(docs, **(options | {"weights": (5, 1), "budget_share": 1.0})).groupBy("source").agg(F.sum(F.col("size") * F.col("copies")).alias("n"))
    assert {r["source"]: r["n"] for r in uneven.collect()} == {"a": 170, "b": 30} or {r["source"]: r["n"] for r in uneven.collect()} == {"a": 160, "b": 30}


def test_targets_of_many_sources(spark):
    rng = random.Random(8)
    sizes = {f"s{i:04d}": int(10 ** rng.uniform(0, 6)) for i in range(500)}
    table = spark.createDataFrame([("0" + k, v) for k, v in sizes.items()], "source_key string, source_size long")
    got = {r["source_key"][1:]: r["target"] for r in budget_mix.source_targets(table).collect()}
    want = reshared(sizes)
    assert got.keys() == want.keys() and all(got[k] == pytest.approx(want[k], rel=1e-9) for k in want)


def test_long_documents_fill_a_large_rest():
    assert fit_budget([80_000, 90_000, 100_000], [1, 1, 1], 95_000) == [0, 1, 0]
    take = fit_budget([70_000, 300_000, 5], [50, 3, 10], 1_234_567)
    assert 0 <= 1_234_567 - (take[0] * 70_000 + take[1] * 300_000 + take[2] * 5) < 70_000


def test_pack_shard_properties():
    rng = random.Random(3)
    for _ in range(100):
        sizes = [rng.randint(1, 64) for _ in range(rng.randint(0, 60))]
        bins, offset, final = pack_shard(sizes, (16, 32, 64), 2.0)
        for b in range(len(final)):
            spans = sorted((offset[i], offset[i] + sizes[i]) for i in range(len(sizes)) if bins[i] == b)
            assert spans[0][0] == 0 and all(x[1] == y[0] for x, y in zip(spans, spans[1:]))
            used = spans[-1][1]
            assert final[b] == min(c for c in (16, 32, 64) if c >= used)


def plain_best_fit(sizes, caps, cost):
    """Bins in a plain list: of those with the least room that is enough, the one filled last."""
    bins, where, left, clock = [], [0] * len(sizes), sum(sizes), 0
    for i in sorted(range(len(sizes)), key=lambda i: (-sizes[i], i)):
        clock += 1
        fits = [b for b in bins if b["room"] >= sizes[i]]
        if fits:
            b = min(fits, key=lambda b: (b["room"], -b["time"]))
        else:
            cap = min((c for c in caps if c >= sizes[i]), key=lambda c: ((c + cost) / min(c, left), c))
            b = {"room": cap, "no": len(bins), "used": 0}
            bins.append(b)
        b["room"], b["used"], b["time"], where[i] = b["room"] - sizes[i], b["used"] + sizes[i], clock, b["no"]
        left -= sizes[i]
    return where, [min(c for c in caps if c >= b["used"]) for b in bins]


def test_pack_shard_equals_plain_best_fit():
    rng = random.Random(11)
    for _ in range(300):
        sizes = [rng.choice([rng.randint(1, 64), rng.randint(1, 9), 16]) for _ in range(rng.randint(0, 80))]
        cost = rng.choice([0.0, 2.0, 16.0])
        bins, _, final = pack_shard(sizes, (16, 32, 64), cost)
        assert (bins.tolist(), final.tolist()) == plain_best_fit(sizes, (16, 32, 64), cost)


def test_pack_keeps_large_ids_beside_a_null(spark):
    ids = [2**53 + 1, 2**53 + 3, -(2**63), 2**63 - 1, None]
    docs = spark.createDataFrame([(i, "a b c", "s") for i in ids], SCHEMA)
    assert {r["doc_id"] for r in pack_documents(docs).collect()} == set(ids)


def test_equal_rows_spread_over_shards(spark):
    docs = spark.createDataFrame([(7, "a b c", "s")] * 300, SCHEMA)
    out = pack_documents(docs, shard_docs=50).toPandas()
    assert len(out) == 300 and out.groupby("shard").size().max() < 100


def test_pack_is_best_fit():
    bins, _, final = pack_shard([60, 50, 14, 4], (64,), 0.0)
    assert bins.tolist() == [0, 1, 1, 0] and final.tolist() == [64, 64]
    assert pack_shard([10], (16, 32, 64), 0.0)[2].tolist() == [16]


def test_pack_documents_whole(spark):
    docs = spark.read.parquet(f"{SF}/documents.parquet")
    out = pack_documents(docs, capacities=(128, 256)).toPandas()
    words = docs.select("doc_id", F.size(F.split(F.trim(F.regexp_replace("text", r"[\x20\x09-\x0D]+", " ")), " ")).alias("n")).toPandas()
    got = out.groupby("doc_id")["n_words"].sum()
    assert got.to_dict() == {i: n for i, n in zip(words["doc_id"], words["n"]) if n}
    use = out.groupby(["shard", "bin"]).agg(n=("n_words", "sum"), cap=("bin_capacity", "first"))
    assert (use["n"] <= use["cap"]).all() and use["n"].sum() / use["cap"].sum() > 0.95


@pytest.mark.parametrize("rows", [[], [(1, None, None)], [(None, "a b", "s"), (1, "", "s"), (1, "a b", "s"), (1, "a b", "s")]])
def test_pack_corner_rows(spark, rows):
    docs = spark.createDataFrame(rows, SCHEMA).withColumn("shard", F.lit("clash")).withColumn("bin", F.lit(1))
    out = pack_documents(docs).toPandas()
    assert out["n_words"].sum() == sum(len((r[1] or "").split()) for r in rows)
