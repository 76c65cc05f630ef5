"""Balance, agreement and accuracy measures."""

from __future__ import annotations

import numpy as np
import pandas as pd
from pyspark.sql import DataFrame, Window
from pyspark.sql import functions as F

from .batching import sum_before
from .kmeans import block_neighbours


def tv_uniform(counts: DataFrame, universe: DataFrame, key: list[str], n: str = "n", by: list[str] | None = None) -> DataFrame:
    """Half the sum of |share - 1/k| over all k nodes of the universe; nodes without points count as share 0."""
    by = by or []
    runs = counts.select(*by).distinct() if by else None
    every = universe.select(*key).distinct()
    every = every.crossJoin(F.broadcast(runs)) if by else every  # a handful of runs
    full = every.join(counts.select(*by, *key, n), [*by, *key], "left").withColumn("__c", F.coalesce(F.col(n), F.lit(0)))
    sums = full.groupBy(*by).agg(F.sum("__c").alias("__t"), F.count("*").alias("__k"))
    joined = full.join(F.broadcast(sums), by) if by else full.crossJoin(F.broadcast(sums))
    gap = F.abs(F.col("__c") / F.col("__t") - 1 / F.col("__k"))
    return joined.groupBy(*by).agg((F.sum(gap) / 2).alias("tv"))


def tv_between(a: DataFrame, b: DataFrame, key: str) -> DataFrame:
    """Total variation between the shares of two subsets."""
    share = lambda df, name: df.groupBy(key).agg(F.count("*").alias("n")).select(
        key, (F.col("n") / F.sum("n").over(Window.partitionBy())).alias(name)
    )
    both = share(a, "p").join(share(b, "q"), key, "full")
    zero = F.lit(0.0)
    return both.agg((F.sum(F.abs(F.coalesce("p", zero) - F.coalesce("q", zero))) / 2).alias("tv"))


def head_share(sizes: DataFrame, m: int, n: str = "n", key: str = "node") -> DataFrame:
    top = sizes.orderBy(F.desc(n), key).limit(m).agg(F.sum(n).alias("h"))
    return top.crossJoin(sizes.agg(F.sum(n).alias("t"))).select((F.col("h") / F.col("t")).alias("head_share"))


def evenness(sizes: DataFrame, n: str = "n") -> DataFrame:
    """Normalised entropy, Gini, max/min and effective number of clusters of positive counts (a node table)."""
    s = sizes.where(F.col(n) > 0).select(F.col(n).cast("double").alias("x"))
    turn = Window.orderBy("x")
    total = s.agg(F.sum("x").alias("t"), F.count("*").alias("k"))
    r = s.withColumn("r", F.row_number().over(turn)).crossJoin(F.broadcast(total)).withColumn("p", F.col("x") / F.col("t"))
    h = -F.sum(F.col("p") * F.log("p"))
    return r.agg(
        (h / F.log(F.greatest(F.max("k"), F.lit(2)))).alias("entropy"),
        (2 * F.sum(F.col("r") * F.col("p")) / F.max("k") - (F.max("k") + 1) / F.max("k")).alias("gini"),
        (F.max("x") / F.min("x")).alias("max_min"),
        F.exp(h).alias("effective"),
    )


def mean_nn_distance(nodes: DataFrame) -> DataFrame:
    """Mean distance to the nearest other centroid of a level (node, centroid); blocks of nodes meet blocks of nodes."""
    rows = nodes.select(F.col("node").alias("point_id"), F.col("centroid").alias("vec"))
    return block_neighbours(rows, rows, 1).agg(F.avg(F.sqrt("dist2")).alias("mean_nn"))


def volume_spread(assigned: DataFrame) -> DataFrame:
    """Coefficient of variation of the clusters' mean radius, single-point clusters left out."""
    r = assigned.groupBy("node").agg(F.avg(F.sqrt("dist2")).alias("r"), F.count("*").alias("n")).where("n > 1")
    return r.agg((F.stddev_pop("r") / F.avg("r")).alias("volume_cv"))


def adjusted_rand(df: DataFrame, a: str, b: str) -> DataFrame:
    """Pair agreement corrected for chance; pair counts in exact decimals."""
    pairs = lambda c: (c.cast("decimal(38,0)") * (c - 1).cast("decimal(38,0)") / 2).cast("decimal(38,0)")
    cells = df.groupBy(a, b).agg(F.count("*").alias("n"))
    one = lambda g: cells.groupBy(g).agg(F.sum("n").alias("n")).agg(F.sum(pairs(F.col("n"))).alias(f"s_{g}"))
    both = cells.agg(F.sum(pairs(F.col("n"))).alias("s"), pairs(F.sum("n")).alias("all"))
    s = both.crossJoin(one(a)).crossJoin(one(b)).select(*[F.col(c).cast("double") for c in ("s", "all", f"s_{a}", f"s_{b}")])
    sa, sb = F.col(f"s_{a}"), F.col(f"s_{b}")
    chance, top = sa * sb / F.col("all"), (sa + sb) / 2
    return s.select(F.when(top == chance, F.when(F.col("s") == top, 1.0).otherwise(0.0)).otherwise((F.col("s") - chance) / (top - chance)).alias("ari"))


def balanced_accuracy(df: DataFrame, truth: str, pred: str) -> DataFrame:
    per = df.groupBy(truth).agg(F.avg((F.col(truth) == F.col(pred)).cast("double")).alias("r"))
    return per.agg(F.avg("r").alias("bacc"))


def roc_auc(df: DataFrame, label: str, score: str) -> DataFrame:
    """Share of (positive, negative) pairs in order, ties one half; works on counts per distinct score, added up
    over range partitions."""
    per = df.groupBy(score).agg(F.sum(label).alias("p"), F.sum(1 - F.col(label)).alias("q"))
    s = sum_before(per, [F.col(score)], "q").withColumn("won", F.col("p") * (F.col("before") + F.col("q") / 2))
    return s.agg((F.sum("won") / (F.sum("p") * F.sum("q"))).alias("auc"))


def roc_auc_by(df: DataFrame, label: str, score: str, by: list[str], digits: int = 4) -> DataFrame:
    """The same for many groups at once, scores in [0, 1] rounded to `digits`: at most 10^digits + 1 rows a group."""
    per = df.groupBy(*by, F.round(score, digits).alias("__s")).agg(F.sum(label).alias("p"), F.sum(1 - F.col(label)).alias("q"))
    earlier = Window.partitionBy(*by).orderBy("__s").rowsBetween(Window.unboundedPreceding, -1)
    s = per.withColumn("won", F.col("p") * (F.coalesce(F.sum("q").over(earlier), F.lit(0)) + F.col("q") / 2))
    pairs = F.sum("p") * F.sum("q")
    return s.groupBy(*by).agg(F.when(pairs > 0, F.sum("won") / pairs).alias("auc"))


def bootstrap_bacc(df: DataFrame, truth: str, pred: str, reps: int = 1000, seed: int = 1) -> DataFrame:
    """Mean and deviation of balanced accuracy over test sets drawn again. A replicate is a multinomial draw
    over the confusion cells, so only K x K counts travel."""
    cells = df.groupBy(truth, pred).agg(F.count("*").alias("n")).orderBy(truth, pred).toPandas()
    rows = cells[truth].rank(method="dense").astype(int).to_numpy() - 1
    n, hit = cells["n"].to_numpy(), (cells[truth] == cells[pred]).to_numpy()

    def run(batches):
        for pdf in batches:
            out = []
            for rep in pdf["id"]:
                draw = np.random.default_rng([seed, int(rep)]).multinomial(n.sum(), n / n.sum())
                all_, good = np.bincount(rows, draw), np.bincount(rows, draw * hit)
                out.append(float((good[all_ > 0] / all_[all_ > 0]).mean()))
            yield pd.DataFrame({"bacc": out})

    return df.sparkSession.range(reps).mapInPandas(run, "bacc double").agg(
        F.avg("bacc").alias("mean"), F.stddev_samp("bacc").alias("std"), F.count("*").alias("reps")
    )


def composition(subset: DataFrame, by: str, cohort: str = "cohort", classes: str | None = None) -> DataFrame:
    """Share of every value of `by`, and of cohort B inside it."""
    per = subset.groupBy(by).agg(
        F.count("*").alias("n"),
        F.avg((F.col(cohort) == "B").cast("double")).alias("share_b"),
        *([F.count_distinct(classes).alias("classes")] if classes else []),
    )
    return per.withColumn("share", F.col("n") / F.sum("n").over(Window.partitionBy()))


def profile_clusters(rows: DataFrame, node: str, features: list[str], cohort: str = "cohort") -> DataFrame:
    """Per node: size, main cohort and its share, mean of each feature."""
    b = F.avg((F.col(cohort) == "B").cast("double"))
    return rows.groupBy(node).agg(
        F.count("*").alias("n"),
        F.when(b > 0.5, "B").otherwise("A").alias("main_cohort"),
        F.greatest(b, 1 - b).alias("main_share"),
        *[F.avg(f).alias(f) for f in features],
    )


def summarise(results: DataFrame) -> DataFrame:
    """Mean per setting, and per setting and family."""
    return results.groupingSets([["setting"], ["setting", "family"]], "setting", "family").agg(F.avg("mean").alias("mean"))


def rank_settings(results: DataFrame) -> DataFrame:
    return results.withColumn("place", F.dense_rank().over(Window.partitionBy("task").orderBy(F.desc("mean"))))


def correlation(a: str, b: str):
    """Pearson correlation over rows where neither is null; null where one of them does not vary."""
    x, y = (F.when(F.col(a).isNotNull() & F.col(b).isNotNull(), F.col(c).cast("double")) for c in (a, b))
    return F.try_divide(F.covar_pop(x, y), F.stddev_pop(x) * F.stddev_pop(y))


def share_score_corr(results: DataFrame, shares: DataFrame, on: list[str]) -> DataFrame:
    return results.join(shares, on).agg(correlation("mean", "share").alias("corr"))


def monte_carlo_auc(scored: DataFrame, label: str = "label", score: str = "score", by: str = "task", run: str = "run") -> DataFrame:
    """Mean and deviation of AUC over runs of held-out scores (by, run, label, score)."""
    each = roc_auc_by(scored, label, score, [by, run])
    return each.groupBy(by).agg(F.avg("auc").alias("mean"), F.stddev_samp("auc").alias("std"), F.count("auc").alias("runs"))


def bootstrap_cells(cells: DataFrame, by: list[str], truth: str = "truth", pred: str = "pred", reps: int = 1000, seed: int = 1) -> DataFrame:
    """Bootstrap of balanced accuracy for many confusion tables at once; one group is at most K x K rows."""

    def run(pdf: pd.DataFrame) -> pd.DataFrame:
        pdf = pdf.sort_values([truth, pred])
        rows, n = pd.factorize(pdf[truth])[0], pdf["n"].to_numpy()
        hit = (pdf[truth] == pdf[pred]).to_numpy()
        draws = np.random.default_rng(seed).multinomial(n.sum(), n / n.sum(), size=reps)
        hot = np.eye(rows.max() + 1)[rows]
        every, good = draws @ hot, (draws * hit) @ hot
        recall = np.divide(good, every, out=np.full(every.shape, np.nan), where=every > 0)
        acc = np.nanmean(recall, axis=1)
        return pd.DataFrame({**{c: [pdf[c].iloc[0]] for c in by}, "mean": [acc.mean()], "std": [acc.std(ddof=1)], "tested": [int(n.sum())]})

    schema = ", ".join([f"{c} string" for c in by] + ["mean double", "std double", "tested long"])
    return cells.groupBy(*by).applyInPandas(run, schema)
