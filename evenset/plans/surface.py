"""Sources, sinks, user functions and the DataFrame forms that have no plain SQL statement."""

from __future__ import annotations

import uuid

import pandas as pd
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from ..operators import batching, kmeans
from ..operators.allocate import fill_level_bisect
from ..sources.tables import shared_folder, table
from .methods import customers, first_vectors, points_of, query, tile_paths

__all__ = ["fresh"]


def fresh(spark) -> str:
    return f"{shared_folder(spark)}/io-{uuid.uuid4().hex}"


def _round_trip(kind: str):
    def run(spark, sf) -> DataFrame:
        df, path = table(spark, sf, "nation"), fresh(spark)
        df.write.format(kind).save(path)
        reader = spark.read.schema(df.schema)
        return (reader if kind == "orc" else reader.option("mode", "FAILFAST")).format(kind).load(path)

    return run


for _kind in ("csv", "json", "orc"):
    query(f"roundtrip_{_kind}", "SELECT * FROM nation")(_round_trip(_kind))


@query("roundtrip_text", "SELECT n_name AS value FROM nation")
def _(spark, sf):
    path = fresh(spark)
    table(spark, sf, "nation").select(F.col("n_name").alias("value")).write.text(path)
    return spark.read.text(path)


@query("scan_binary_files")
def _(spark, sf):
    # the length of what was read, not of the directory entry: without its content a file is only listed
    return spark.read.format("binaryFile").load(f"{sf}/nation.parquet").select("path", F.length("content").cast("long").alias("length"))


@query("sink_partitioned", "SELECT c_mktsegment, count(*) AS n FROM customer GROUP BY 1")
def _(spark, sf):
    path = fresh(spark)
    table(spark, sf, "customer").write.partitionBy("c_mktsegment").parquet(path)
    return spark.read.parquet(path).groupBy("c_mktsegment").agg(F.count("*").alias("n"))


@query("sink_dynamic_overwrite", "SELECT n_regionkey, count(*) AS n FROM nation GROUP BY 1")
def _(spark, sf):
    path, df = fresh(spark), table(spark, sf, "nation")
    df.write.partitionBy("n_regionkey").parquet(path)
    # the second write touches one partition and leaves the others
    df.where("n_regionkey = 1").write.mode("overwrite").option("partitionOverwriteMode", "dynamic").partitionBy("n_regionkey").parquet(path)
    return spark.read.schema(df.schema).parquet(path).groupBy("n_regionkey").agg(F.count("*").alias("n"))


@query("sink_sorted_ranges", "SELECT o_orderkey FROM orders")
def _(spark, sf):
    path = fresh(spark)
    df = table(spark, sf, "orders").select("o_orderkey")
    df.repartitionByRange(4, "o_orderkey").sortWithinPartitions("o_orderkey").write.option("maxRecordsPerFile", 5000).parquet(path)
    return spark.read.parquet(path)


@query("join_salted_skew", "SELECT d.doc_id, n FROM documents d JOIN (SELECT lang, count(*) AS n FROM documents GROUP BY 1) l USING (lang)")
def _(spark, sf):
    docs = table(spark, sf, "documents").select("doc_id", "lang")
    small = docs.groupBy("lang").agg(F.count("*").alias("n")).withColumn("salt", F.explode(F.sequence(F.lit(0), F.lit(15))))
    return docs.withColumn("salt", F.pmod(F.xxhash64("doc_id"), F.lit(16)).cast("int")).join(small, ["lang", "salt"]).select("doc_id", "n")


@query("global_ordinal_by_range", "SELECT c_custkey, row_number() OVER (ORDER BY c_acctbal, c_custkey) - 1 AS ordinal FROM customer")
def _(spark, sf):
    df = table(spark, sf, "customer").select("c_custkey", "c_acctbal")
    return batching.global_ordinal(df, [F.col("c_acctbal"), F.col("c_custkey")]).select("c_custkey", "ordinal")


@query("set_union_by_name", "SELECT c_nationkey AS k, c_custkey AS id FROM customer UNION ALL SELECT s_nationkey, s_suppkey FROM supplier")
def _(spark, sf):
    a = table(spark, sf, "customer").select(F.col("c_nationkey").alias("k"), F.col("c_custkey").alias("id"))
    return a.unionByName(table(spark, sf, "supplier").select(F.col("s_suppkey").alias("id"), F.col("s_nationkey").alias("k")))


@query("set_intersect_all", "SELECT c_nationkey AS k FROM customer INTERSECT ALL SELECT s_nationkey FROM supplier")
def _(spark, sf):
    return table(spark, sf, "customer").select(F.col("c_nationkey").alias("k")).intersectAll(table(spark, sf, "supplier").select("s_nationkey"))


@query("sample_bernoulli")
def _(spark, sf):
    return table(spark, sf, "documents").select("doc_id").sample(fraction=0.1, seed=1)


@query("sample_by_class")
def _(spark, sf):
    return table(spark, sf, "documents").select("doc_id", "lang").sampleBy("lang", {"en": 0.1, "fr": 0.3}, seed=1)


@query("split_random")
def _(spark, sf):
    a, b = table(spark, sf, "documents").select("doc_id").randomSplit([0.8, 0.2], seed=1)
    return a.withColumn("part", F.lit("train")).unionByName(b.withColumn("part", F.lit("test")))


@query("agg_approx_distinct")
def _(spark, sf):
    return table(spark, sf, "events").agg(F.approx_count_distinct("user_id").alias("users"), F.hll_sketch_estimate(F.hll_sketch_agg("event_id")).alias("ids"))


_NORM = "SELECT vec_id AS point_id, round(list_sum([CAST(x AS DOUBLE) * x FOR x IN embedding]), 5) AS n FROM embeddings"


@query("udf_arrow_sq_dist", _NORM)
def _(spark, sf):
    @F.pandas_udf("double")
    def sq(v: pd.Series) -> pd.Series:
        return v.map(lambda x: float((x * x).sum()))

    return points_of(spark, sf).select("point_id", F.round(sq("vec"), 5).alias("n"))


@query("udf_scalar_python", "SELECT n_nationkey, length(n_name) AS n FROM nation")
def _(spark, sf):
    size = F.udf(lambda s: len(s), "bigint")
    return table(spark, sf, "nation").select("n_nationkey", size("n_name").alias("n"))


@query("udaf_tv_uniform", "WITH c AS (SELECT c_mktsegment AS g, c_nationkey, count(*)::DOUBLE AS n FROM customer GROUP BY ALL) SELECT g, round(sum(abs(n / t - 1.0::DOUBLE / k)) / 2, 6) AS tv FROM (SELECT *, sum(n) OVER (PARTITION BY g) AS t, count(*) OVER (PARTITION BY g) AS k FROM c) x GROUP BY g")
def _(spark, sf):
    @F.pandas_udf("double")
    def tv(n: pd.Series) -> float:
        return float((n / n.sum() - 1 / len(n)).abs().sum() / 2)

    c = table(spark, sf, "customer").groupBy(F.col("c_mktsegment").alias("g"), "c_nationkey").agg(F.count("*").cast("double").alias("n"))
    return c.groupBy("g").agg(F.round(tv("n"), 6).alias("tv"))


@query(
    "udtf_fill_level",
    "WITH s AS (SELECT n_regionkey, c_nationkey, count(*) AS s FROM customer JOIN nation ON c_nationkey = n_nationkey GROUP BY ALL), "
    "t AS (SELECT n_regionkey, cap, sum(least(s, cap)) AS total FROM s, unnest(range(0, (SELECT max(s) + 1 FROM s))) AS u(cap) GROUP BY ALL HAVING cap <= max(s)) "
    "SELECT n_regionkey, arg_min(cap, (abs(total - 60), cap)) AS cap FROM t GROUP BY n_regionkey",
)
def _(spark, sf):
    """Cap per region by a table function, one call per row of collected sizes."""

    @F.udtf(returnType="cap long")
    class FillLevel:
        def eval(self, sizes: list, budget: int):
            yield (fill_level_bisect([int(x) for x in sizes], int(budget)),)

    spark.udtf.register("evenset_fill_level", FillLevel)
    sizes = customers(spark, sf).groupBy("n_regionkey", "c_nationkey").agg(F.count("*").alias("s")).groupBy("n_regionkey").agg(F.sort_array(F.collect_list("s")).alias("sizes"))
    return spark.sql("SELECT n_regionkey, cap FROM {s}, LATERAL evenset_fill_level(sizes, 60)", s=sizes)


@query("map_in_pandas_assign", "SELECT count(*) AS n FROM embeddings")
def _(spark, sf):
    return kmeans.assign(points_of(spark, sf), first_vectors(spark, sf, 10)).agg(F.count("*").alias("n"))


@query("apply_cogrouped_compare", "SELECT a.lang, n_docs, n_tiles FROM (SELECT lang, count(*) AS n_docs FROM documents GROUP BY 1) a JOIN (SELECT lang, CAST(sum((length(text) + 223) // 224) AS BIGINT) AS n_tiles FROM documents GROUP BY 1) b USING (lang)")
def _(spark, sf):
    a = table(spark, sf, "documents").groupBy("lang").agg(F.count("*").alias("n"))
    b = tile_paths(spark, sf).groupBy("lang").agg(F.count("*").alias("n"))
    both = lambda x, y: pd.DataFrame({"lang": x["lang"], "n_docs": x["n"], "n_tiles": y["n"]})
    return a.groupBy("lang").cogroup(b.groupBy("lang")).applyInPandas(both, "lang string, n_docs long, n_tiles long")
