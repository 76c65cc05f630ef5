"""Mixing sources to target word budgets by subset sums.

Documents are counted by exact length. A source's target is met by whole passes over it plus a remainder;
the remainder takes an even share of every length, then the longest lengths that still fit, and a bounded
knapsack over what is left closes the last `slack` words. Documents of a length are picked by seeded hash.
Sources are ranked and filled up in range partitions, so their number is not bounded by one task.

Defined cases: null texts have size 0 and are never taken; null sources are one source, last in order;
each row is taken by itself, whatever ids occur again; equal rows are interchangeable. A document is taken at most
max_repeats times, rounded up.
"""

from __future__ import annotations

import math

import pandas as pd
from pyspark.sql import DataFrame, SparkSession, Window
from pyspark.sql import functions as F

from .shared import keep_table, read_table, sums_before, word_count

BUCKETS = 64


def bounded_subset(lengths: list[int], counts: list[int], budget: int) -> list[int]:
    """How many of each length to take so that the sum is the greatest not above budget."""
    take = [0] * len(lengths)
    if budget <= 0:
        return take
    reach, mask = 1, (1 << (budget + 1)) - 1
    trail: list[tuple[int, int, int]] = []
    for i, (size, n) in enumerate(zip(lengths, counts)):
        n = min(n, budget // size) if size > 0 else 0
        chunk = 1
        while n > 0 and not reach >> budget & 1:
            k = min(chunk, n)
            trail.append((i, k, reach))
            reach |= (reach << (k * size)) & mask
            n, chunk = n - k, chunk * 2
        if reach >> budget & 1:
            break
    at = reach.bit_length() - 1
    for i, k, before in reversed(trail):
        if not before >> at & 1:
            take[i] += k
            at -= k * lengths[i]
    return take


def fit_budget(lengths: list[int], counts: list[int], budget: int, slack: int = 16384) -> list[int]:
    """Copies (at most one per document) of each length whose sum comes nearest below budget."""
    total = sum(a * b for a, b in zip(lengths, counts))
    if budget >= total:
        return list(counts)
    take = [n * budget // total for n in counts]
    left = budget - sum(a * b for a, b in zip(lengths, take))
    order = sorted(range(len(lengths)), key=lambda i: -lengths[i])
    for i in order:
        k = min(counts[i] - take[i], max(0, left - slack) // lengths[i])
        take[i] += k
        left -= k * lengths[i]
    while left > 4 * slack:  # too much for the knapsack: the longest that fit, until it is not or none fits
        found = next((i for i in order if counts[i] > take[i] and lengths[i] <= left), None)
        if found is None:
            break
        k = min(counts[found] - take[found], max(1, (left - 2 * slack) // lengths[found]), left // lengths[found])
        take[found] += k
        left -= k * lengths[found]
    # long lengths first reach the budget in few steps, short ones then fill the gap
    rest = [i for i in order if lengths[i] <= left and counts[i] > take[i]]
    more = bounded_subset([lengths[i] for i in rest], [counts[i] - take[i] for i in rest], left if rest else 0)
    for i, k in zip(rest, more):
        take[i] += k
    return take


def source_targets(
    sizes: DataFrame, *, weights: tuple[float, ...] = (3, 1, 2), budget_share: float = 1.5, max_repeats: float = 2.0
) -> DataFrame:
    """source_key, source_size -> source_key, source_size, target. Sources that would pass max_repeats times their
    size stop there and the excess goes to the others by weight; found in one pass over the sources in the order in
    which they fill up."""
    ranked = sums_before(sizes, [F.col("source_key")], {"turn": F.lit(1)})
    pick = F.element_at(F.array(*[F.lit(float(w)) for w in weights]), (F.col("turn") % len(weights) + 1).cast("int"))
    ranked = ranked.withColumn("weight", pick).withColumn("most", max_repeats * F.col("source_size"))
    filled = sums_before(
        ranked, [F.col("most") / F.col("weight"), F.col("source_key")], {"full": F.col("most"), "w_full": F.col("weight")}
    )
    filled = keep_table(filled, "filled")
    every = filled.agg((budget_share * F.sum("source_size")).alias("budget"), F.sum("weight").alias("w_all"))
    # the filled total is the least of the lines full + level * rest of weights, so the level is their greatest root
    root = (F.col("budget") - F.col("full")) / (F.col("w_all") - F.col("w_full"))
    level = filled.join(F.broadcast(every)).agg(F.max(root).alias("level"))  # one row each
    target = F.least("most", F.col("level") * F.col("weight")).alias("target")
    return filled.join(F.broadcast(level)).select("source_key", "source_size", target)


def _plan(max_repeats: float):
    most = math.ceil(max_repeats)

    def run(pdf: pd.DataFrame) -> pd.DataFrame:
        pdf = pdf.sort_values("size")
        lengths, counts = [int(x) for x in pdf["size"]], [int(x) for x in pdf["n_docs"]]
        total, goal = sum(a * b for a, b in zip(lengths, counts)), int(round(pdf["target"].iloc[0]))
        passes = min(most, goal // total) if total else 0
        extra = fit_budget(lengths, counts, goal - passes * total) if passes < most else [0] * len(lengths)
        return pd.DataFrame({"source_key": pdf["source_key"], "size": lengths, "passes": passes, "extra": extra})

    return run


def plan_mix(
    docs: DataFrame,
    *,
    id_col: str = "doc_id",
    source_col: str = "source",
    text_col: str = "text",
    seed: int = 17,
    weights: tuple[float, ...] = (3, 1, 2),
    budget_share: float = 1.5,
    max_repeats: float = 2.0,
    with_row: bool = False,
) -> DataFrame:
    """Per row: doc_id, source, size, source_size, target and copies (0 to max_repeats); with_row adds the row itself
    as a struct. Rows are numbered inside hash buckets of a (source, length), so that no length of a source meets in
    one task."""
    key = F.when(F.col(source_col).isNull(), "1").otherwise(F.concat(F.lit("0"), F.col(source_col)))
    mixed = F.xxhash64(F.col(id_col), F.col(text_col), F.lit(seed))
    rows = docs.select(
        F.col(id_col).alias("doc_id"),
        key.alias("source_key"),
        word_count(F.col(text_col)).alias("size"),
        F.pmod(mixed, F.lit(BUCKETS)).alias("bucket"),
        F.xxhash64(mixed, F.lit(seed + 1)).alias("turn"),
        *([F.struct(*[F.col(f"`{c}`") for c in docs.columns]).alias("row")] if with_row else []),
    )
    plain = rows.drop("row")
    if not with_row:
        plain = rows = keep_table(rows, "sizes")
    counts = keep_table(plain.groupBy("source_key", "size", "bucket").agg(F.count("*").alias("n")), "size-counts")
    lengths = counts.groupBy("source_key", "size").agg(F.sum("n").alias("n_docs"))
    sizes = lengths.groupBy("source_key").agg(F.sum(F.col("size") * F.col("n_docs")).alias("source_size"))
    goals = source_targets(sizes, weights=weights, budget_share=budget_share, max_repeats=max_repeats)
    goals = keep_table(goals, "targets")
    plan = (
        lengths.where("size > 0")
        .join(goals.select("source_key", "target"), "source_key")
        .groupBy("source_key")
        .applyInPandas(_plan(max_repeats), "source_key string, size long, passes int, extra long")
    )
    run = Window.partitionBy("source_key", "size").orderBy("bucket").rowsBetween(Window.unboundedPreceding, -1)
    starts = (
        counts.withColumn("before", F.coalesce(F.sum("n").over(run), F.lit(0)))
        .join(plan, ["source_key", "size"], "left")
        .join(goals, "source_key")
        .select("source_key", "size", "bucket", "passes", (F.col("extra") - F.col("before")).alias("quota"), "source_size", "target")
    )
    turn = Window.partitionBy("source_key", "size", "bucket").orderBy("turn", "doc_id")
    picked = rows.withColumn("place", F.row_number().over(turn)).join(starts, ["source_key", "size", "bucket"])
    copies = F.coalesce(F.col("passes") + (F.col("place") <= F.col("quota")).cast("int"), F.lit(0))
    return picked.select(
        "doc_id",
        F.when(F.col("source_key") == "1", F.lit(None)).otherwise(F.substring("source_key", 2, 1 << 30)).alias("source"),
        "size",
        "source_size",
        "target",
        copies.cast("int").alias("copies"),
        *(["row"] if with_row else []),
    )


def mix_documents(docs: DataFrame, **options) -> DataFrame:
    """The mixed corpus: every row as often as planned, columns unchanged. Takes the options of plan_mix."""
    plan = plan_mix(docs, with_row=True, **options)
    out = plan.where("copies > 0").withColumn("copy", F.explode(F.sequence(F.lit(1), F.col("copies"))))
    return out.select(*[F.col("row").getField(c).alias(c) for c in docs.columns])


def op2_budget_mix(spark: SparkSession, sf_dir: str) -> DataFrame:
    plan = plan_mix(read_table(spark, sf_dir, "documents"))
    return plan.select(
        "doc_id", "size", "source_size", "target", (F.col("size") * F.col("copies")).cast("long").alias("taken")
    )
