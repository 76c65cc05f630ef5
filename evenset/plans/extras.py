"""Seeding, fixed trees, further selections and plans, bucketed sink, plan source, vectorised and table functions."""

from __future__ import annotations

import uuid
from collections.abc import Iterator

import numpy as np
import pandas as pd
import pyarrow as pa
from pyspark.sql import functions as F
from pyspark.sql.datasource import DataSource, DataSourceReader, InputPartition

from ..functions.linalg import nearest, to_matrix
from ..operators import allocate, batching, features, kmeans, metrics, tree
from ..sources.tables import class_label, fit_width, make_tiles, slides, staged, table
from .methods import (
    _CLASSED, _D2, _PTS, _curate_sql, _DRAW, _steps_sql, SQL, TILES, alloc_sql, both_built, first_vectors, paths_of, points_of,
    query, r, small_subset, tile_paths,
)
from .surface import fresh

_NEAREST = f"WITH {_steps_sql(10, 0)} SELECT vec_id AS point_id, node FROM a0"


# Seeding ----------------------------------------------------------------------------------------------------


def _seed_sql(k: int, pick: str) -> str:
    """Unrolled rounds: s{i} holds the i-th seed, d{i} the distance of every point to the nearest seed so far."""
    parts = [_PTS, "s0 AS (SELECT vec_id, v FROM p ORDER BY md5(concat('1:', vec_id)), vec_id LIMIT 1)"]
    for i in range(k - 1):
        near = f"least(q.d, {_D2})" if i else _D2
        join = f"JOIN d{i - 1} q USING (vec_id)" if i else ""
        parts.append(f"d{i} AS (SELECT p.vec_id, p.v, {near} AS d FROM p {join}, s{i} c)")
        parts.append(f"s{i + 1} AS (SELECT vec_id, v FROM d{i} WHERE d > 0 ORDER BY {pick.format(i=i)}, vec_id LIMIT 1)")
    return f"WITH {', '.join(parts)} " + " UNION ALL ".join(f"SELECT {i} AS turn, vec_id AS point_id FROM s{i}" for i in range(k))


def _seeds(spark, seeds):
    return spark.createDataFrame([(i, p) for i, p in enumerate(seeds)], "turn int, point_id long")


@query("seed_farthest_first", _seed_sql(5, "d DESC"))
def _(spark, sf):
    return _seeds(spark, kmeans.seed_passes(points_of(spark, sf), 5, how="farthest")[0])


_RACE = "-ln((CAST(concat('0x', substr(md5(concat({i} + 2, ':', vec_id)), 1, 8)) AS BIGINT) + 0.5::DOUBLE) / 4294967296.0::DOUBLE) / d"


@query("seed_plusplus_md5", _seed_sql(4, _RACE))
def _(spark, sf):
    return _seeds(spark, kmeans.seed_passes(points_of(spark, sf), 4, how="race")[0])


# Trees with fixed seeds --------------------------------------------------------------------------------------

_FIXED = ["c0 AS (SELECT vec_id AS node, v FROM p WHERE vec_id < 24)", f"a AS (SELECT vec_id AS point_id, arg_min(node, (d, node)) AS c1 FROM (SELECT p.vec_id, c.node, {_D2} AS d FROM p, c0 c) x GROUP BY vec_id)"]
for _low, _k, _name in (("c0", 8, "u2"), ("u2t", 3, "u3")):
    _FIXED.append(
        f"{_name} AS (SELECT p.node AS below, arg_min(c.node, ({_D2}, c.node)) AS above FROM {_low} p, (SELECT * FROM c0 WHERE node < {_k}) c GROUP BY p.node), "
        f"{_name}t AS (SELECT * FROM c0 WHERE node < {_k})"
    )
_FIXED_SQL = f"WITH {_PTS}, {', '.join(_FIXED)}"


def fixed_tree(spark, sf):
    levels = [first_vectors(spark, sf, k) for k in (24, 8, 3)]
    of = kmeans.assign(points_of(spark, sf), levels[0]).select("point_id", F.col("node").alias("c1"), "dist2")
    return tree.ClusterTree(levels, [nearest(a, b)[0] for a, b in zip(levels, levels[1:])], of)


@query("tree_paths_fixed", f"{_FIXED_SQL} SELECT point_id, c1, u2.above AS c2, u3.above AS c3 FROM a JOIN u2 ON c1 = u2.below JOIN u3 ON u2.above = u3.below")
def _(spark, sf):
    return fixed_tree(spark, sf).paths().select("point_id", "c1", "c2", "c3")


@query("tree_sizes_fixed", f"{_FIXED_SQL} SELECT node, count(point_id) AS n FROM u2t LEFT JOIN (SELECT point_id, u2.above AS node FROM a JOIN u2 ON c1 = u2.below) z USING (node) GROUP BY node")
def _(spark, sf):
    return fixed_tree(spark, sf).sizes(2).select("node", "n")


@query("tree_persisted", f"{_FIXED_SQL} SELECT u3.above AS c3, count(*) AS n FROM a JOIN u2 ON c1 = u2.below JOIN u3 ON u2.above = u3.below GROUP BY 1")
def _(spark, sf):
    path = fresh(spark)
    fixed_tree(spark, sf).save(path)
    return tree.load_tree(spark, path).paths().groupBy("c3").agg(F.count("*").alias("n"))


@query("tree_route_leaf", f"WITH {_steps_sql(24, 0)} SELECT vec_id AS point_id, node AS c1 FROM a0")
def _(spark, sf):
    return fixed_tree(spark, sf).route(points_of(spark, sf), "leaf").select("point_id", "c1")


def _down(into: str, at: str, kids: str, extra: str = "") -> str:
    """SQL of one step down: the nearest child of the node that a point has reached."""
    return (
        f"{into} AS (SELECT p.vec_id, arg_min(c.vec_id, ({_D2}, c.vec_id)) AS node{extra} FROM p JOIN {at} t ON t.vec_id = p.vec_id "
        f"JOIN {kids} k ON k.above = t.node JOIN p c ON c.vec_id = k.below GROUP BY p.vec_id)"
    )


@query(
    "tree_route_greedy",
    f"{_FIXED_SQL}, g3 AS (SELECT p.vec_id, arg_min(c.vec_id, ({_D2}, c.vec_id)) AS node FROM p JOIN p c ON c.vec_id < 3 GROUP BY p.vec_id), "
    f"{_down('g2', 'g3', 'u3')}, {_down('g1', 'g2', 'u2', f', min({_D2}) AS d')} SELECT vec_id AS point_id, node AS c1, round(d, 6) AS dist2 FROM g1",
)
def _(spark, sf):
    return fixed_tree(spark, sf).route(points_of(spark, sf), "greedy").select("point_id", "c1", r("dist2").alias("dist2"))


@query("cluster_volume_spread", f"WITH {_steps_sql(8, 0)} SELECT round(stddev_pop(x) / avg(x), 6) AS volume_cv FROM (SELECT node, avg(sqrt(d)) AS x FROM a0 GROUP BY node HAVING count(*) > 1) y")
def _(spark, sf):
    return metrics.volume_spread(kmeans.assign(points_of(spark, sf), first_vectors(spark, sf, 8))).select(r("volume_cv").alias("volume_cv"))


@query(
    "kmeans_sse_fixed",
    f"WITH {_steps_sql(8, 2)} " + " UNION ALL ".join(f"SELECT {i} AS step, round(sum(d), 4) AS sse FROM a{i}" for i in range(3)),
)
def _(spark, sf):
    """Within-cluster sum of squares per step from fixed seeds."""
    m = kmeans.kmeans_fit(points_of(spark, sf), 8, init=first_vectors(spark, sf, 8), max_iter=3, tol=-1)
    return spark.createDataFrame([(i, round(float(s), 4)) for i, s in enumerate(m.history)], "step int, sse double")


@query("kmeans_sse_history")
def _(spark, sf):
    """Within-cluster sum of squares per step, for every way to seed."""
    p, rows = staged(points_of(spark, sf)), []
    for init in ("random", "plusplus", "parallel", kmeans.seed_passes(p, 10, how="race")[1]):
        m = kmeans.kmeans_fit(p, 10, init=init, max_iter=5, tol=-1)
        rows += [(init if isinstance(init, str) else "exact_race", i, float(s)) for i, s in enumerate(m.history)]
    return spark.createDataFrame(rows, "seeding string, step int, sse double")


@query("assign_strategies_agree", f"WITH {_steps_sql(10, 0)} SELECT s AS strategy, node, count(*) AS n FROM a0, (VALUES ('blocked'), ('broadcast_gemm'), ('expr')) AS v(s) GROUP BY ALL")
def _(spark, sf):
    out, c = None, first_vectors(spark, sf, 10)
    for s in ("expr", "broadcast_gemm", "blocked"):
        one = kmeans.assign(points_of(spark, sf), c, strategy=s).groupBy(F.lit(s).alias("strategy"), "node").agg(F.count("*").alias("n"))
        out = one if out is None else out.unionByName(one)
    return out


def _library(kind: str):
    def run(spark, sf):
        from pyspark.ml import clustering
        from pyspark.ml.functions import array_to_vector

        rows = points_of(spark, sf).select("point_id", array_to_vector("vec").alias("features"))
        model = getattr(clustering, kind)(k=10, seed=1, maxIter=5).fit(rows)
        return model.transform(rows).groupBy(F.col("prediction").alias("node")).agg(F.count("*").alias("n"))

    return run


query("baseline_mlkmeans")(_library("KMeans"))
query("baseline_bisecting")(_library("BisectingKMeans"))


@query("tree_population_weighted")
def _(spark, sf):
    """The contrast: centroids weighted by population; TV of the pool over top nodes, both ways."""
    p, out = points_of(spark, sf), None
    for w in ("one", "population"):
        s = tree.build_tree(p, [40, 12, 4], centroid_weight=w).sizes(3)
        one = metrics.tv_uniform(s, s, ["node"]).select(F.lit(w).alias("centroid_weight"), "tv")
        out = one if out is None else out.unionByName(one)
    return out


# Other forms of tiles and vectors ----------------------------------------------------------------------------


@query("tiles_fit_width", f"WITH {TILES} SELECT tile_id, rpad(content, 224, ' ') AS content FROM t")
def _(spark, sf):
    tiles = make_tiles(table(spark, sf, "documents"))
    return fit_width(tiles.select("tile_id", "content"), "content", 224)


_DOT = "list_sum([z[1] * z[2] FOR z IN list_zip(p.v, c.v)])"


@query(
    "assign_cosine",
    f"WITH {_PTS}, q AS (SELECT p.vec_id AS point_id, c.vec_id AS node, {_DOT} / sqrt(list_sum([x * x FOR x IN p.v]) * list_sum([x * x FOR x IN c.v])) AS cosine "
    "FROM p JOIN p c ON c.vec_id < 10) SELECT point_id, arg_min(node, (-cosine, node)) AS node, round(abs(2 - 2 * max(cosine)), 6) AS dist2 FROM q GROUP BY point_id",
)
def _(spark, sf):
    """Vectors of unequal length, brought to unit length: the nearest by squared distance is the nearest by angle."""
    p = points_of(spark, sf)
    long = p.withColumn("vec", F.transform("vec", lambda x: x * (F.col("point_id") % 7 + 1)))
    c = first_vectors(spark, sf, 10)
    c = c / np.linalg.norm(c, axis=1, keepdims=True)
    return kmeans.assign(features.normalise(long), c).select("point_id", "node", r("dist2").alias("dist2"))


# Further selections ------------------------------------------------------------------------------------------


@query(
    "curate_flat_clusters",
    f"WITH {alloc_sql('100', ['node'], _steps_sql(8, 0) + ', t AS (SELECT vec_id AS tile_id, node FROM a0)')}, {_DRAW.format(by='node', g='g0')} SELECT tile_id AS point_id, node FROM d WHERE rk <= granted",
)
def _(spark, sf):
    a = kmeans.assign(points_of(spark, sf), first_vectors(spark, sf, 8))
    return allocate.curate_even(a, "node", 100).select("point_id", "node")


_STAT = _CLASSED.replace("SELECT *, CASE", "SELECT *, concat(CASE", 1).replace("END AS class FROM t0", "END, CASE WHEN slide_id IN (SELECT doc_id FROM documents WHERE length(text) >= 2000) THEN ':long' ELSE ':short' END) AS class FROM t0")


@query("curate_by_label_and_stat", _curate_sql(1125, ["class"]).replace(TILES, _STAT))
def _(spark, sf):
    """Slide label crossed with a simple statistic of the slide: its length."""
    long = table(spark, sf, "documents").select(F.col("doc_id").alias("slide_id"), F.when(F.length("text") >= 2000, ":long").otherwise(":short").alias("band"))
    label = class_label(slides(spark, sf)).join(long, "slide_id").select("slide_id", F.concat("class", "band").alias("class"))
    return allocate.curate_even(tile_paths(spark, sf).join(label, "slide_id"), "class", 1125).select("point_id", "slide_id")


def _spread_sql(k: int, take: int) -> str:
    parts = [_steps_sql(k, 0), "m AS (SELECT a0.vec_id, node, v, d FROM a0 JOIN p USING (vec_id))"]
    parts.append("s0 AS (SELECT node, arg_min(vec_id, (d, vec_id)) AS vec_id FROM m GROUP BY node)")
    parts.append(f"e0 AS (SELECT p.vec_id, p.node, p.v, {_D2} AS d FROM m p JOIN s0 USING (node) JOIN m c ON c.vec_id = s0.vec_id)")
    for i in range(1, take):
        parts.append(f"s{i} AS (SELECT node, arg_max(vec_id, (d, -vec_id)) AS vec_id FROM e{i - 1} WHERE d > 0 GROUP BY node)")
        parts.append(f"e{i} AS (SELECT p.vec_id, p.node, p.v, least(p.d, {_D2}) AS d FROM e{i - 1} p JOIN s{i} USING (node) JOIN m c ON c.vec_id = s{i}.vec_id)")
    return f"WITH {', '.join(parts)} " + " UNION ALL ".join(f"SELECT vec_id AS point_id, node FROM s{i}" for i in range(take))


@query("apply_grouped_spread", _spread_sql(8, 3))
def _(spark, sf):
    p = points_of(spark, sf).select("point_id", "vec")
    a = kmeans.assign(p, first_vectors(spark, sf, 8)).join(p, "point_id")
    return allocate.draw_by_distance(a, 3, "spread").select("point_id", "node")


# Further plans -----------------------------------------------------------------------------------------------


@query(
    "batches_replace",
    "WITH h AS (SELECT doc_id AS point_id, row_number() OVER (ORDER BY doc_id) - 1 AS ordinal, count(*) OVER () AS n FROM documents) "
    "SELECT id // 16 AS iteration, CAST(id % 16 AS INTEGER) AS slot, point_id FROM unnest(range(0, 16 * 120)) AS u(id) "
    "JOIN h ON ordinal = CAST('0x' || substr(md5(concat('17:', id)), 1, 15) AS BIGINT) % n",
)
def _(spark, sf):
    return batching.plan_shuffled(small_subset(spark, sf), 16, 120, mode="replace")


@query("batches_strict")
def _(spark, sf):
    s = small_subset(spark, sf).withColumn("cluster", F.concat_ws(":", "lang", "source"))
    return batching.plan_stratified(s, "cluster", 96, 30, strict=True)


@query("plan_exported", SQL["batches_shuffled"])
def _(spark, sf):
    path = fresh(spark)
    batching.write_plan(batching.plan_shuffled(small_subset(spark, sf), 16, 120), path)
    return spark.read.parquet(path)


@query("plan_cost", "SELECT CAST(least(1920, 4 * count(*)) AS BIGINT) AS fed, round(least(1920, 4 * count(*)) / count(*)::DOUBLE, 6) AS subset_passes FROM documents")
def _(spark, sf):
    s = small_subset(spark, sf)
    p = batching.plan_shuffled(s, 16, 120).withColumn("epoch", F.lit(0))
    return batching.plan_cost(p, s, s).select("fed", r("subset_passes").alias("subset_passes"))


class _Range(InputPartition):
    def __init__(self, first: int, last: int):
        self.first, self.last = first, last


class PlanReader(DataSourceReader):
    def __init__(self, options):
        self.sizes = [int(x) for x in options["sizes"].split(",")]
        self.batch, self.rounds = int(options["batch"]), int(options["iterations"])
        self.parts = int(options.get("parts", "4"))

    def partitions(self):
        cuts = [self.rounds * i // self.parts for i in range(self.parts + 1)]
        return [_Range(a, b) for a, b in zip(cuts, cuts[1:]) if b > a]

    def read(self, part):
        k = len(self.sizes)
        q, surplus = divmod(self.batch, k)
        for t in range(part.first, part.last):
            for o, s in enumerate(self.sizes):
                start = t * q + (t * surplus - o + k - 1) // k
                for j in range(start, (t + 1) * q + ((t + 1) * surplus - o + k - 1) // k):
                    yield t, o, j // s, j % s


class PlanSource(DataSource):
    """Draws of a stratified plan by ranges of iterations: options sizes (per cluster), batch, iterations, parts."""

    @classmethod
    def name(cls):
        return "evenset_plan"

    def schema(self):
        return "iteration long, cluster_no long, pass long, place long"

    def reader(self, schema):
        return PlanReader(self.options)


@query(
    "plan_datasource",
    "WITH z AS (SELECT count(*) AS s, row_number() OVER (ORDER BY lang) - 1 AS o, count(*) OVER () AS k FROM documents GROUP BY lang), "
    "g AS (SELECT t, e, CASE WHEN e < (15 // k) * k THEN e % k ELSE (t * (15 % k) + e - (15 // k) * k) % k END AS o FROM unnest(range(0, 30)) AS u(t), unnest(range(0, 15)) AS w(e), (SELECT any_value(k) AS k FROM z)), "
    "j AS (SELECT t, o, row_number() OVER (PARTITION BY o ORDER BY t, e) - 1 AS j FROM g) SELECT t AS iteration, o AS cluster_no, j // s AS pass, j % s AS place FROM j JOIN z USING (o)",
)
def _(spark, sf):
    spark.dataSource.register(PlanSource)
    sizes = [x["count"] for x in table(spark, sf, "documents").groupBy("lang").count().orderBy("lang").collect()]
    return spark.read.format("evenset_plan").options(sizes=",".join(map(str, sizes)), batch=15, iterations=30).load()


@query("sink_bucketed", "SELECT l_orderkey, count(*) AS n FROM lineitem JOIN orders ON l_orderkey = o_orderkey GROUP BY 1")
def _(spark, sf):
    """Two tables bucketed on the join key: the join reads bucket by bucket without an exchange."""
    names = {}
    for name, key in (("lineitem", "l_orderkey"), ("orders", "o_orderkey")):
        names[name] = f"evenset_{name}_{uuid.uuid4().hex}"
        df = table(spark, sf, name).select(F.col(key).alias("k"), F.lit(name).alias("side"))
        df.write.bucketBy(8, "k").sortBy("k").option("path", fresh(spark)).saveAsTable(names[name])
    a, b = spark.table(names["lineitem"]), spark.table(names["orders"]).select("k").hint("merge")
    return a.join(b, "k").groupBy(F.col("k").alias("l_orderkey")).agg(F.count("*").alias("n"))


# Vectorised and table functions -------------------------------------------------------------------------------


@query("udf_iterator_route", _NEAREST)
def _(spark, sf):
    held = spark.sparkContext.broadcast(first_vectors(spark, sf, 10))  # 10 x 64 numbers

    @F.pandas_udf("long")
    def route(parts: Iterator[pd.Series]) -> Iterator[pd.Series]:
        c = held.value
        for v in parts:
            yield pd.Series(nearest(to_matrix(v), c)[0] if len(v) else np.zeros(0, int))

    return points_of(spark, sf).select("point_id", route("vec").alias("node"))


@query("map_in_arrow_assign", _NEAREST)
def _(spark, sf):
    c = first_vectors(spark, sf, 10)

    def run(batches):
        for b in batches:
            if b.num_rows:
                x = b.column("vec").flatten().to_numpy().reshape(b.num_rows, -1)
                yield pa.RecordBatch.from_arrays([b.column("point_id"), pa.array(nearest(x, c)[0])], ["point_id", "node"])

    return points_of(spark, sf).select("point_id", "vec").mapInArrow(run, "point_id long, node long")


@query("udaf_vector_mean", "SELECT label, CAST(i - 1 AS INTEGER) AS i, round(avg(embedding[i]::DOUBLE), 6) AS x FROM embeddings, unnest(range(1, 65)) AS u(i) GROUP BY ALL")
def _(spark, sf):
    """Partial vectors per slice of a label first: no label, however large, is one task's input."""

    @F.pandas_udf("array<double>")
    def total(v: pd.Series) -> np.ndarray:
        return to_matrix(v).sum(axis=0)

    part = points_of(spark, sf).groupBy("label", F.pmod(F.xxhash64("point_id"), F.lit(16)).alias("salt"))
    n = points_of(spark, sf).groupBy("label").agg(F.count("*").alias("n"))
    cells = part.agg(total("vec").alias("s")).select("label", F.posexplode("s").alias("i", "s")).groupBy("label", "i").agg(F.sum("s").alias("s"))
    return cells.join(n, "label").select("label", "i", F.round(F.col("s") / F.col("n"), 6).alias("x"))


@query("udtf_tile_text", f"WITH {TILES} SELECT slide_id, pos, content FROM t")
def _(spark, sf):
    @F.udtf(returnType="pos int, content string")
    class TileText:
        def eval(self, text: str, width: int):
            for i in range(0, len(text or ""), width):
                yield i // width, text[i : i + width]

    spark.udtf.register("evenset_tile_text", TileText)
    return spark.sql("SELECT doc_id AS slide_id, pos, content FROM {d}, LATERAL evenset_tile_text(text, 224)", d=table(spark, sf, "documents"))


@query(
    "sql_registered_functions",
    "SELECT doc_id, (length(text) + 223) // 224 AS n_tiles, upper(substr(lang, 1, 1)) || substr(lang, 2) AS title FROM documents",
)
def _(spark, sf):
    spark.sql("CREATE OR REPLACE TEMPORARY FUNCTION evenset_tiles(n BIGINT) RETURNS BIGINT RETURN (n + 223) div 224")
    spark.udf.register("evenset_title", F.pandas_udf(lambda s: s.str.capitalize(), "string"))
    return spark.sql("SELECT doc_id, evenset_tiles(length(text)) AS n_tiles, evenset_title(lang) AS title FROM {d}", d=table(spark, sf, "documents"))


# Alignment of subsets with the pool ---------------------------------------------------------------------------


@query("share_convergence")
def _(spark, sf):
    """TV of tissue shares between subset and pool as the subset grows, for both trees."""
    out, lang = None, tile_paths(spark, sf).select("point_id", "lang")
    for shape, t in both_built(spark, sf):
        paths = staged(paths_of(t).join(lang, "point_id"))
        for percent in (1, 5, 10, 20, 50, 100):
            sub = allocate.curate(paths, ["c4", "c3", "c2", "c1"], fraction=percent / 100)
            one = metrics.tv_between(sub, paths, "lang").select(F.lit(shape).alias("tree"), F.lit(percent).alias("percent"), "tv")
            out = one if out is None else out.unionByName(one)
    return out


@query("project_vectors")
def _(spark, sf):
    """Principal and random projections of the base vectors to eight numbers."""
    p = points_of(spark, sf)
    a = features.pca_project(p, 8).select("point_id", F.lit("pca").alias("how"), "vec")
    return a.unionByName(features.random_project(p, 64, 8).select("point_id", F.lit("random").alias("how"), "vec"))
