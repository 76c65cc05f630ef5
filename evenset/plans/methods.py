"""The methods on the given tables, with SQL twins wherever the answer is exact."""

from __future__ import annotations

from pyspark.sql import DataFrame, SparkSession, Window
from pyspark.sql import functions as F

from ..functions.linalg import dot, lloyd, priority, sq_dist, to_matrix
from ..operators import allocate, batching, features, kmeans, metrics, projection, tree
from ..sources.tables import VISIBLE, class_label, detect_regions, make_tiles, slides, spread, staged, table, visible_text

LEVELS = ["lang", "ls", "slide_id"]
Q: dict = {}
SQL: dict[str, str] = {}


def query(name: str, sql: str | None = None):
    def wrap(f):
        Q[name] = f
        if sql:
            SQL[name] = sql
        return f

    return wrap


def r(col, digits=6):
    return F.round(col, digits)


# Tiles of documents with their path in the natural tree language > language:source > document.
TILES = (
    "t AS (SELECT doc_id * 1048576 + pos AS tile_id, doc_id AS slide_id, CAST(pos AS INTEGER) AS pos, lang, "
    "concat(lang, ':', source) AS ls, source, substr(text, CAST(pos * 224 + 1 AS BIGINT), 224) AS content "
    "FROM documents, unnest(range(0, CAST((length(text) + 223) // 224 AS BIGINT))) AS u(pos))"
)


def doc_tiles(spark, sf):
    return make_tiles(table(spark, sf, "documents"))


def tile_paths(spark, sf):
    """Tiles without content, on their path; counted from lengths, no text is cut."""
    docs = table(spark, sf, "documents")
    n = F.expr("cast((length(text) + 223) div 224 as int)")
    rows = docs.where("length(text) > 0").select(
        "lang", F.concat_ws(":", "lang", "source").alias("ls"), "source", F.col("doc_id").alias("slide_id"),
        F.explode(F.sequence(F.lit(0), n - 1)).alias("pos"),
    )
    return rows.withColumn("point_id", F.col("slide_id") * (1 << 20) + F.col("pos"))


def doc_leaves(spark, sf):
    docs = table(spark, sf, "documents").where("length(text) > 0")
    return docs.select(
        "lang", F.concat_ws(":", "lang", "source").alias("ls"), F.col("doc_id").alias("slide_id"),
        F.expr("(length(text) + 223) div 224").alias("size"),
    )


@query("tiles_from_documents", f"WITH {TILES} SELECT tile_id, slide_id, pos, content FROM t")
def _(spark, sf):
    return doc_tiles(spark, sf)


@query(
    "tiles_foreground_filter",
    f"WITH {TILES} SELECT tile_id FROM t WHERE len(regexp_extract_all(content, '[A-Za-zÀ-ÿ]')) >= 0.5 * length(content)",
)
def _(spark, sf):
    return detect_regions(doc_tiles(spark, sf)).select("tile_id")


def _visible_sql() -> str:
    t = "html"
    for p in VISIBLE:
        t = f"regexp_replace({t}, '{p}', ' ', 'g')"
    return f"trim(regexp_replace({t}, '[ \\t\\r\\n]+', ' ', 'g'))"


@query(
    "pages_visible_text_tiles",
    f"WITH p AS (SELECT page_id, {_visible_sql()} AS text FROM pages) SELECT page_id * 1048576 + pos AS tile_id, page_id AS slide_id, "
    "CAST(pos AS INTEGER) AS pos, substr(text, CAST(pos * 224 + 1 AS BIGINT), 224) AS content FROM p, unnest(range(0, CAST((length(text) + 223) // 224 AS BIGINT))) AS u(pos)",
)
def _(spark, sf):
    return make_tiles(visible_text(table(spark, sf, "pages")), id_col="page_id")


_CELLS = (
    f"{TILES}, c AS (SELECT tile_id, (31 * unicode(substr(lower(content), i, 1)) + unicode(substr(lower(content), i + 1, 1))) % 64 AS bucket "
    "FROM t, unnest(range(1, CAST(length(content) AS BIGINT))) AS u(i)), b AS (SELECT tile_id, CAST(bucket AS INTEGER) AS bucket, count(*) AS n FROM c GROUP BY ALL)"
)


@query("tile_bigram_features", f"WITH {_CELLS} SELECT tile_id, bucket, n FROM b")
def _(spark, sf):
    return features.bigram_cells(doc_tiles(spark, sf)).select("tile_id", F.col("bucket").cast("int").alias("bucket"), "n")


@query("tile_vector_norms", f"WITH {_CELLS} SELECT tile_id, round(sqrt(CAST(sum(n * n) AS DOUBLE)), 6) AS norm FROM b GROUP BY tile_id")
def _(spark, sf):
    """Norm before scaling, by way of the largest component of the Arrow form's unit vector."""
    tiles = doc_tiles(spark, sf).where("length(content) > 1")
    top = features.bigram_cells(tiles).groupBy("tile_id").agg(F.max("n").alias("n"))
    unit = features.hash_embed(tiles).select(F.col("point_id").alias("tile_id"), F.array_max("vec").alias("x"))
    return unit.join(top, "tile_id").select("tile_id", r(F.col("n") / F.col("x")).alias("norm"))


@query(
    "handmade_features",
    f"WITH {TILES} SELECT tile_id, round(len(regexp_extract_all(content, '[A-Za-zÀ-ÿ]')) / length(content)::DOUBLE, 6) AS letters, "
    "round(len(regexp_extract_all(content, '[0-9]')) / length(content)::DOUBLE, 6) AS digits, "
    "round(len(regexp_extract_all(content, '[.,;:!?]')) / length(content)::DOUBLE, 6) AS punctuation, CAST(strpos(content, chr(10)) AS DOUBLE) AS first_break FROM t",
)
def _(spark, sf):
    f = features.handmade_features(doc_tiles(spark, sf))
    return f.select(
        "tile_id", r("intensity.letters").alias("letters"), r("intensity.digits").alias("digits"),
        r("matrix.punctuation").alias("punctuation"), F.col("layout.first_break").alias("first_break"),
    )


_COHORT = "CASE WHEN CAST(substr(source, 4) AS INTEGER) < 10 THEN 'A' ELSE 'B' END"


@query("pool_distribution", f"WITH {TILES} SELECT lang, {_COHORT} AS cohort, count(*) AS n FROM t GROUP BY ROLLUP (lang, {_COHORT})")
def _(spark, sf):
    cohort = F.when(F.substring("source", 4, 10).cast("int") < 10, "A").otherwise("B")
    return tile_paths(spark, sf).withColumn("cohort", cohort).rollup("lang", "cohort").agg(F.count("*").alias("n"))


# Points, seeds and Lloyd steps ------------------------------------------------------------------------------


def points_of(spark, sf):
    return table(spark, sf, "embeddings").select(
        F.col("vec_id").alias("point_id"), F.transform("embedding", lambda x: x.cast("double")).alias("vec"), "label"
    )


def first_vectors(spark, sf, k):
    rows = points_of(spark, sf).where(F.col("point_id") < k).orderBy("point_id").collect()
    return to_matrix([x["vec"] for x in rows])


_PTS = "p AS (SELECT vec_id, [CAST(x AS DOUBLE) FOR x IN embedding] AS v FROM embeddings)"
_D2 = "list_sum([(z[1] - z[2]) * (z[1] - z[2]) FOR z IN list_zip(p.v, c.v)])"


def _steps_sql(k: int, steps: int) -> str:
    parts = [_PTS, f"c0 AS (SELECT vec_id AS node, v FROM p WHERE vec_id < {k})"]
    for i in range(steps + 1):
        parts.append(
            f"a{i} AS (SELECT vec_id, arg_min(node, (d, node)) AS node, min(d) AS d FROM (SELECT p.vec_id, c.node, {_D2} AS d FROM p, c{i} c) x GROUP BY vec_id)"
        )
        parts.append(
            f"m{i} AS (SELECT node, i, avg(p.v[i]) AS x FROM a{i} JOIN p USING (vec_id), unnest(range(1, 65)) AS u(i) GROUP BY node, i)"
        )
        parts.append(f"c{i + 1} AS (SELECT node, list(x ORDER BY i) AS v FROM m{i} GROUP BY node)")
    return ", ".join(parts)


@query("assign_nearest_fixed", f"WITH {_steps_sql(10, 0)} SELECT vec_id AS point_id, node, round(d, 6) AS dist2 FROM a0")
def _(spark, sf):
    return kmeans.assign(points_of(spark, sf), first_vectors(spark, sf, 10), strategy="expr").select("point_id", "node", r("dist2").alias("dist2"))


def _steps(spark, sf, k, steps):
    p = points_of(spark, sf)
    model = kmeans.kmeans_fit(p, k, init=first_vectors(spark, sf, k), max_iter=steps, tol=-1)
    return kmeans.assign(p, model.centroids).groupBy("node").agg(F.count("*").alias("n"), r(F.sum("dist2"), 4).alias("sse"))


for _name, _n in (("kmeans_one_step", 1), ("kmeans_three_steps", 3)):
    query(_name, f"WITH {_steps_sql(8, _n)} SELECT node, count(*) AS n, round(sum(d), 4) AS sse FROM a{_n} GROUP BY node")(
        lambda spark, sf, n=_n: _steps(spark, sf, 8, n)
    )


@query(
    "resample_closest_per_cluster",
    f"WITH {_steps_sql(8, 0)} SELECT vec_id AS point_id, node FROM (SELECT *, row_number() OVER (PARTITION BY node ORDER BY d, vec_id) AS r FROM a0) x WHERE r <= 5",
)
def _(spark, sf):
    a = kmeans.assign(points_of(spark, sf), first_vectors(spark, sf, 8))
    return kmeans.closest_per_node(a, 5).select("point_id", "node")


@query("curate_closest_in_leaf", SQL["resample_closest_per_cluster"].replace("r <= 5", "r <= 3"))
def _(spark, sf):
    a = kmeans.assign(points_of(spark, sf), first_vectors(spark, sf, 8))
    return allocate.draw_by_distance(a, 3).select("point_id", "node")


@query(
    "tree_two_level_fixed",
    f"WITH {_PTS}, c0 AS (SELECT vec_id AS node, v FROM p WHERE vec_id < 12), a AS (SELECT vec_id, arg_min(node, (d, node)) AS c1 FROM (SELECT p.vec_id, c.node, {_D2} AS d FROM p, c0 c) x GROUP BY vec_id), "
    f"b AS (SELECT vec_id AS c1, arg_min(node, (d, node)) AS c2 FROM (SELECT p.vec_id, c.node, {_D2} AS d FROM (SELECT node AS vec_id, v FROM c0) p, (SELECT * FROM c0 WHERE node < 3) c) x GROUP BY vec_id) "
    "SELECT vec_id AS point_id, c1, c2 FROM a JOIN b USING (c1)",
)
def _(spark, sf):
    leaves = first_vectors(spark, sf, 12)
    top = first_vectors(spark, sf, 3)
    of = kmeans.assign(points_of(spark, sf), leaves).select("point_id", F.col("node").alias("c1"), "dist2")
    from ..functions.linalg import nearest

    return tree.ClusterTree([leaves, top], [nearest(leaves, top)[0]], of).paths().select("point_id", "c1", "c2")


# Allocation and sampling on the natural tree ----------------------------------------------------------------


def alloc_sql(budget: str, levels: list[str], source: str = TILES, runs: str | None = None, exact: bool = False, size: str = "count(*)") -> str:
    """CTEs g0, g1, ... by brute force over all caps."""
    key = ["run"] if runs else []
    parts = [source] + ([f"runs AS ({runs})"] if runs else [])
    for i, level in enumerate(levels):
        above = key + levels[:i]
        cols = ", ".join([*levels[:i], level])
        parts.append(f"n{i} AS (SELECT {cols}, CAST({size} AS BIGINT) AS size FROM t GROUP BY {cols})")
        if i == 0:
            parts.append(f"b0 AS (SELECT n0.*, {budget} FROM n0, runs)" if runs else f"b0 AS (SELECT n0.*, CAST({budget} AS BIGINT) AS budget FROM n0)")
        else:
            up = ", ".join(levels[:i])
            extra = "p.run, " if runs else ""
            parts.append(f"b{i} AS (SELECT n{i}.*, {extra}p.granted AS budget FROM n{i} JOIN g{i - 1} p USING ({up}))")
        by = ", ".join(above) if above else "1 = 1"
        sel = f"{', '.join(above)}, " if above else ""
        parts.append(
            f"f{i} AS (SELECT {sel}n, CAST(sum(least(n, size)) AS BIGINT) AS total, any_value(budget) AS budget FROM b{i}, unnest(range(0, budget + 1)) AS u(n) GROUP BY {sel}n)"
        )
        pick = "max(n) FILTER (WHERE total <= budget AND n <= budget)" if exact else "arg_min(n, (abs(budget - total), n))"
        parts.append(f"k{i} AS (SELECT {sel}{pick} AS cap FROM f{i} GROUP BY {by})")
        join = f"USING ({', '.join(above)})" if above else "ON true"
        if exact:
            w = f"PARTITION BY {', '.join(above)}" if above else ""
            wo = f"PARTITION BY {', '.join([*above, 'size > cap'])}"
            parts.append(f"h{i} AS (SELECT b{i}.*, least(cap, 1000000000) AS cap FROM b{i} JOIN k{i} {join})")
            parts.append(
                f"g{i} AS (SELECT * EXCLUDE (rest, turn), least(cap, size) + CASE WHEN size > cap AND turn <= rest THEN 1 ELSE 0 END AS granted FROM (SELECT *, budget - sum(least(cap, size)) OVER ({w}) AS rest, "
                f"row_number() OVER ({wo} ORDER BY md5(concat('17:', CAST({level} AS VARCHAR))), {level}) AS turn FROM h{i}) x)"
            )
        else:
            parts.append(f"g{i} AS (SELECT b{i}.*, cap, least(cap, size) AS granted FROM b{i} JOIN k{i} {join})")
    return ", ".join(parts)


@query("allocate_lang_source_doc", f"WITH {alloc_sql('1125', LEVELS)} SELECT lang, ls, slide_id, size, budget, cap, granted FROM g2")
def _(spark, sf):
    g = allocate.allocate_tree(doc_leaves(spark, sf), LEVELS, 1125)["slide_id"]
    return g.select("lang", "ls", "slide_id", "size", "budget", "cap", "granted")


@query(
    "allocate_exact_rounding",
    f"WITH {alloc_sql('1125', LEVELS, exact=True)} SELECT lang, ls, slide_id, size, budget, CAST(granted AS BIGINT) AS granted FROM (SELECT * REPLACE (CAST(budget AS BIGINT) AS budget) FROM g2)",
)
def _(spark, sf):
    g = allocate.allocate_tree(doc_leaves(spark, sf), LEVELS, 1125, rounding="exact")["slide_id"]
    return g.select("lang", "ls", "slide_id", "size", "budget", "granted")


_DRAW = "d AS (SELECT t.*, granted, row_number() OVER (PARTITION BY {by} ORDER BY md5(concat('17:', CAST(tile_id AS VARCHAR))), tile_id) AS rk FROM t JOIN {g} g USING ({by}))"


def _curate_sql(budget, levels, out="tile_id AS point_id, slide_id"):
    last = f"g{len(levels) - 1}"
    return f"WITH {alloc_sql(str(budget), levels)}, {_DRAW.format(by=', '.join(levels), g=last)} SELECT {out} FROM d WHERE rk <= granted"


@query("curate_lang_source_tiles", _curate_sql(1125, LEVELS))
def _(spark, sf):
    return allocate.curate(tile_paths(spark, sf), LEVELS, budget=1125).select("point_id", "slide_id")


@query("curate_start_lower_level", _curate_sql(1125, LEVELS[1:]))
def _(spark, sf):
    return allocate.curate(tile_paths(spark, sf), LEVELS, budget=1125, start="ls").select("point_id", "slide_id")


_CLASS = f"CASE WHEN {_COHORT} = 'A' THEN concat('A:', lang) ELSE concat('B:', lang, ':', source) END"
_CLASSED = TILES.replace("t AS (", "t0 AS (", 1) + f", t AS (SELECT *, {_CLASS} AS class FROM t0)"


@query("curate_label_balanced", _curate_sql(1125, ["class"]).replace(TILES, _CLASSED))
def _(spark, sf):
    label = class_label(slides(spark, sf)).select("slide_id", "class")
    return allocate.curate_even(tile_paths(spark, sf).join(label, "slide_id"), "class", 1125).select("point_id", "slide_id")


@query("curate_uniform", f"WITH {TILES} SELECT tile_id AS point_id FROM t ORDER BY md5(concat('17:', CAST(tile_id AS VARCHAR))), tile_id LIMIT 1125")
def _(spark, sf):
    return allocate.select_uniform(tile_paths(spark, sf), 1125).select("point_id")


@query("curate_full_pool", f"WITH {TILES} SELECT tile_id AS point_id FROM t")
def _(spark, sf):
    return tile_paths(spark, sf).select("point_id")


_CUST = "t AS (SELECT c_custkey AS tile_id, c_nationkey, n_regionkey FROM customer JOIN nation ON c_nationkey = n_nationkey)"


def customers(spark, sf):
    return table(spark, sf, "customer").join(F.broadcast(table(spark, sf, "nation")), F.col("c_nationkey") == F.col("n_nationkey")).select(
        F.col("c_custkey").alias("point_id"), "c_nationkey", "n_regionkey"
    )


@query(
    "curate_region_nation_customers",
    f"WITH {alloc_sql('150', ['n_regionkey', 'c_nationkey'], _CUST)}, {_DRAW.format(by='n_regionkey, c_nationkey', g='g1')} SELECT tile_id AS point_id, c_nationkey FROM d WHERE rk <= granted",
)
def _(spark, sf):
    return allocate.curate(customers(spark, sf), ["n_regionkey", "c_nationkey"], budget=150).select("point_id", "c_nationkey")


@query("fill_level_customers", f"WITH {alloc_sql('300', ['n_regionkey', 'c_nationkey'], _CUST)} SELECT DISTINCT n_regionkey, cap, budget FROM g1")
def _(spark, sf):
    leaves = customers(spark, sf).groupBy("n_regionkey", "c_nationkey").agg(F.count("*").alias("size"))
    return allocate.allocate_tree(leaves, ["n_regionkey", "c_nationkey"], 300)["c_nationkey"].select("n_regionkey", "cap", "budget").distinct()


@query("fill_level_flat_events", f"WITH {alloc_sql('500', ['user_id'], 't AS (SELECT user_id FROM events)')} SELECT user_id, size, cap, granted FROM g0")
def _(spark, sf):
    leaves = table(spark, sf, "events").groupBy("user_id").agg(F.count("*").alias("size"))
    return allocate.allocate_tree(leaves, ["user_id"], 500)["user_id"].select("user_id", "size", "cap", "granted")


# A grid of budgets in one plan: every run is a key of the allocation.
_RUNS = "SELECT f AS run, CAST(round(f * (SELECT count(*) FROM t) / 100.0) AS BIGINT) AS budget FROM (VALUES (1), (10), (50)) AS v(f)"


def grid_leaves(spark, sf, fractions=(1, 10, 50)):
    leaves = doc_leaves(spark, sf)
    runs = spark.createDataFrame([(f,) for f in fractions], "run int")
    total = leaves.agg(F.sum("size").alias("__t"))
    return leaves.crossJoin(F.broadcast(runs)).crossJoin(F.broadcast(total)).withColumn("budget", F.round(F.col("run") * F.col("__t") / 100.0).cast("long")).drop("__t")


def grid(spark, sf, levels=LEVELS, fractions=(1, 10, 50)):
    return allocate.allocate_tree(grid_leaves(spark, sf, fractions), levels, "budget", keys=["run"])


_GRID = alloc_sql("runs.run, runs.budget", ["lang", "ls"], runs=_RUNS)


@query("curate_fraction_grid", f"WITH {_GRID} SELECT run, lang, ls, size, granted FROM g1")
def _(spark, sf):
    return grid(spark, sf, ["lang", "ls"])["ls"].select("run", "lang", "ls", "size", "granted")


@query(
    "saturation_report",
    f"WITH {_GRID} SELECT run, round(avg(CASE WHEN granted >= size THEN 1.0 ELSE 0.0 END), 6) AS exhausted, round(avg(CASE WHEN granted = 0 THEN 1.0 ELSE 0.0 END), 6) AS starved, CAST(sum(granted) - any_value(budget0) AS BIGINT) AS miss "
    "FROM g1 JOIN (SELECT run AS r0, budget AS budget0 FROM runs) z ON run = r0 GROUP BY run",
)
def _(spark, sf):
    g = allocate.saturation(grid(spark, sf, ["lang", "ls"])["ls"])
    want = grid_leaves(spark, sf).groupBy("run").agg(F.max("budget").alias("b"))
    out = g.groupBy("run").agg(r(F.avg(F.col("exhausted").cast("double"))).alias("exhausted"), r(F.avg(F.col("starved").cast("double"))).alias("starved"), F.sum("granted").alias("s"))
    return out.join(want, "run").select("run", "exhausted", "starved", (F.col("s") - F.col("b")).alias("miss"))


@query(
    "exhaust_budget",
    "WITH s AS (SELECT c_nationkey, count(*) AS size FROM customer GROUP BY 1), f AS (SELECT a.c_nationkey, CAST(sum(least(a.size - 1, b.size)) AS BIGINT) AS lo, CAST(sum(least(a.size, b.size)) AS BIGINT) AS hi FROM s a, s b GROUP BY 1) "
    "SELECT c_nationkey, (lo + hi) // 2 + 1 AS budget FROM f",
)
def _(spark, sf):
    s = table(spark, sf, "customer").groupBy("c_nationkey").agg(F.count("*").alias("size"))
    w = Window.orderBy("size", "c_nationkey")
    f = s.withColumn("before", F.coalesce(F.sum("size").over(w.rowsBetween(Window.unboundedPreceding, -1)), F.lit(0))).withColumn("m", F.count("*").over(Window.partitionBy()) - F.row_number().over(w) + 1)
    f = f.withColumn("hi", F.col("before") + F.col("m") * F.col("size"))
    # children of the same size all lose one when the cap drops by one
    same = f.groupBy("size").agg(F.max("m").alias("ms"))
    lo = F.col("hi") - F.col("ms")
    return f.join(same, "size").select("c_nationkey", (F.floor((lo + F.col("hi")) / 2) + 1).cast("long").alias("budget"))


@query("prune_exact_copies", "SELECT md5(text) AS digest, min(doc_id) AS doc_id, count(*) AS copies FROM documents GROUP BY 1")
def _(spark, sf):
    return allocate.prune_copies(table(spark, sf, "documents"), "text", "doc_id")


@query(
    "retrieve_neighbours",
    f"WITH {_PTS} SELECT seed, vec_id AS point_id FROM (SELECT c.vec_id AS seed, p.vec_id, row_number() OVER (PARTITION BY c.vec_id ORDER BY {_D2}, p.vec_id) AS r FROM p, p c WHERE c.vec_id < 10 AND p.vec_id <> c.vec_id) x WHERE r <= 5",
)
def _(spark, sf):
    p = points_of(spark, sf)
    seeds = p.where("point_id < 10").select(F.col("point_id").alias("seed"), F.col("vec").alias("sv"))
    pairs = p.crossJoin(F.broadcast(seeds)).where("point_id <> seed")  # ten stated seeds
    turn = Window.partitionBy("seed").orderBy(sq_dist(F.col("vec"), F.col("sv")), "point_id")
    return pairs.withColumn("r", F.row_number().over(turn)).where("r <= 5").select("seed", "point_id")


@query("retrieve_neighbours_hundredths", SQL["retrieve_neighbours"].replace("c.vec_id < 10", "c.vec_id % 100 = 0"))
def _(spark, sf):
    """Every row whose id is divisible by 100 as query, against all rows."""
    p = points_of(spark, sf)
    return kmeans.block_neighbours(p, p.where("point_id % 100 = 0"), 5).select("seed", "point_id")


# Measures ---------------------------------------------------------------------------------------------------


def _tv_sql(table_name, node, run="run"):
    return (
        f"SELECT {run}, round(sum(abs(c / t - 1.0::DOUBLE / k)) / 2, 6) AS tv FROM (SELECT {run}, granted::DOUBLE AS c, sum(granted) OVER (PARTITION BY {run})::DOUBLE AS t, count(*) OVER (PARTITION BY {run}) AS k FROM (SELECT {run}, {node}, sum(granted) AS granted FROM {table_name} GROUP BY ALL) y) x GROUP BY {run}"
    )


@query("balance_curve_natural", f"WITH {_GRID} SELECT a.run, a.tv AS tv_lang, b.tv AS tv_ls FROM ({_tv_sql('g1', 'lang')}) a JOIN ({_tv_sql('g1', 'ls')}) b USING (run)")
def _(spark, sf):
    g = grid(spark, sf, ["lang", "ls"])["ls"]
    out = None
    for node in ("lang", "ls"):
        c = g.groupBy("run", node).agg(F.sum("granted").alias("n"))
        tv = metrics.tv_uniform(c, c, [node], by=["run"]).select("run", r("tv").alias(f"tv_{node}"))
        out = tv if out is None else out.join(tv, "run")
    return out


@query(
    "tv_uniform_levels",
    f"WITH {TILES}, a AS (SELECT lang, count(*)::DOUBLE AS c FROM t GROUP BY 1), b AS (SELECT ls, count(*)::DOUBLE AS c FROM t GROUP BY 1) "
    "SELECT 'lang' AS level, round(sum(abs(c / t - 1.0::DOUBLE / k)) / 2, 6) AS tv FROM a, (SELECT sum(c) AS t, count(*) AS k FROM a) UNION ALL SELECT 'ls', round(sum(abs(c / t - 1.0::DOUBLE / k)) / 2, 6) FROM b, (SELECT sum(c) AS t, count(*) AS k FROM b)",
)
def _(spark, sf):
    t = tile_paths(spark, sf)
    parts = []
    for level in ("lang", "ls"):
        c = t.groupBy(level).agg(F.count("*").alias("n"))
        parts.append(metrics.tv_uniform(c, c, [level]).select(F.lit(level).alias("level"), r("tv").alias("tv")))
    return parts[0].unionByName(parts[1])


@query(
    "tv_subset_vs_pool",
    _curate_sql(1125, LEVELS, "lang").replace("SELECT lang FROM d WHERE rk <= granted", "SELECT round(sum(abs(p - q)) / 2, 6) AS tv FROM (SELECT coalesce(a.p, 0) AS p, coalesce(b.q, 0) AS q FROM (SELECT lang, count(*)::DOUBLE / sum(count(*)) OVER () AS p FROM d WHERE rk <= granted GROUP BY 1) a FULL JOIN (SELECT lang, count(*)::DOUBLE / sum(count(*)) OVER () AS q FROM t GROUP BY 1) b USING (lang)) y"),
)
def _(spark, sf):
    t = tile_paths(spark, sf)
    return metrics.tv_between(allocate.curate(t, LEVELS, budget=1125), t, "lang").select(r("tv").alias("tv"))


@query("head_share", f"WITH {TILES}, s AS (SELECT ls, count(*) AS n FROM t GROUP BY 1) SELECT round((SELECT sum(n) FROM (SELECT n FROM s ORDER BY n DESC, ls LIMIT 2) x)::DOUBLE / sum(n), 6) AS head_share FROM s")
def _(spark, sf):
    s = tile_paths(spark, sf).groupBy(F.col("ls").alias("node")).agg(F.count("*").alias("n"))
    return metrics.head_share(s, 2).select(r("head_share").alias("head_share"))


@query(
    "evenness_measures",
    f"WITH {TILES}, s AS (SELECT count(*)::DOUBLE AS x FROM t GROUP BY ls), k AS (SELECT x, row_number() OVER (ORDER BY x) AS r, count(*) OVER () AS k, x / sum(x) OVER () AS p FROM s) "
    "SELECT round(-sum(p * ln(p)) / ln(max(k)), 6) AS entropy, round(2 * sum(r * p) / max(k) - (max(k) + 1) / max(k)::DOUBLE, 6) AS gini, round(max(x) / min(x), 6) AS max_min, round(exp(-sum(p * ln(p))), 4) AS effective FROM k",
)
def _(spark, sf):
    e = metrics.evenness(tile_paths(spark, sf).groupBy("ls").agg(F.count("*").alias("n")))
    return e.select(r("entropy").alias("entropy"), r("gini").alias("gini"), r("max_min").alias("max_min"), r("effective", 4).alias("effective"))


@query(
    "mean_nn_distance",
    f"WITH {_PTS}, l AS (SELECT label, i, avg(embedding[i]::DOUBLE) AS x FROM embeddings, unnest(range(1, 65)) AS u(i) GROUP BY ALL), m AS (SELECT label, list(x ORDER BY i) AS v FROM l GROUP BY label) "
    f"SELECT round(avg(sqrt(d)), 6) AS mean_nn FROM (SELECT p.label, min({_D2}) AS d FROM m p, m c WHERE p.label <> c.label GROUP BY 1) x",
)
def _(spark, sf):
    nodes = label_means(points_of(spark, sf)).select(F.col("label").alias("node"), F.col("c").alias("centroid"))
    return metrics.mean_nn_distance(nodes).select(r("mean_nn").alias("mean_nn"))


@query(
    "adjusted_rand_lang_source",
    "WITH c AS (SELECT lang, source, count(*)::DOUBLE AS n FROM documents GROUP BY ALL), s AS (SELECT sum(n * (n - 1) / 2) AS s, sum(n) AS m FROM c), "
    "a AS (SELECT sum(x * (x - 1) / 2) AS sa FROM (SELECT sum(n) AS x FROM c GROUP BY lang)), b AS (SELECT sum(x * (x - 1) / 2) AS sb FROM (SELECT sum(n) AS x FROM c GROUP BY source)) "
    "SELECT round((s - sa * sb / (m * (m - 1) / 2)) / ((sa + sb) / 2 - sa * sb / (m * (m - 1) / 2)), 8) AS ari FROM s, a, b",
)
def _(spark, sf):
    return metrics.adjusted_rand(table(spark, sf, "documents"), "lang", "source").select(r("ari", 8).alias("ari"))


@query(
    "balanced_accuracy_centroid_rule",
    f"WITH {_PTS}, l AS (SELECT vec_id, label FROM embeddings), c AS (SELECT label, list(x ORDER BY i) AS v FROM (SELECT label, i, avg(p.v[i]) AS x FROM p JOIN l USING (vec_id), unnest(range(1, 65)) AS u(i) GROUP BY label, i) y GROUP BY label), "
    f"g AS (SELECT vec_id, arg_min(label, (d, label)) AS pred FROM (SELECT p.vec_id, c.label, {_D2} AS d FROM p, c) z GROUP BY 1) SELECT round(avg(rc), 6) AS bacc FROM (SELECT label, avg(CASE WHEN label = pred THEN 1.0 ELSE 0.0 END) AS rc FROM g JOIN l USING (vec_id) GROUP BY label) w",
)
def _(spark, sf):
    return metrics.balanced_accuracy(centroid_rule(spark, sf), "label", "pred").select(r("bacc").alias("bacc"))


def label_means(p):
    rows = p.select("label", F.posexplode("vec").alias("i", "x")).groupBy("label", "i").agg(F.avg("x").alias("x"))
    return rows.groupBy("label").agg(F.transform(F.array_sort(F.collect_list(F.struct("i", "x"))), lambda s: s["x"]).alias("c"))


def centroid_rule(spark, sf):
    p = points_of(spark, sf)
    c = label_means(p)
    best = p.crossJoin(F.broadcast(c.withColumnRenamed("label", "pred"))).groupBy("point_id", "label").agg(
        F.min(F.struct(sq_dist(F.col("vec"), F.col("c")), "pred")).alias("b")
    )
    return best.select("point_id", "label", F.col("b.pred").alias("pred"))


@query("bootstrap_bacc")
def _(spark, sf):
    return metrics.bootstrap_bacc(centroid_rule(spark, sf), "label", "pred", reps=1000)


@query(
    "composition_by_cohort",
    f"WITH {TILES}, q AS (SELECT lang, {_COHORT} AS cohort FROM t) SELECT lang, count(*) AS n, round(avg(CASE WHEN cohort = 'B' THEN 1.0 ELSE 0.0 END), 6) AS share_b, round(count(*)::DOUBLE / sum(count(*)) OVER (), 6) AS share FROM q GROUP BY lang",
)
def _(spark, sf):
    cohort = F.when(F.substring("source", 4, 10).cast("int") < 10, "A").otherwise("B")
    c = metrics.composition(tile_paths(spark, sf).withColumn("cohort", cohort), "lang")
    return c.select("lang", "n", r("share_b").alias("share_b"), r("share").alias("share"))


@query("classes_touched", "WITH " + _CLASSED + " SELECT lang, count(DISTINCT class) AS classes FROM t GROUP BY lang")
def _(spark, sf):
    return class_label(slides(spark, sf)).where("n_tiles > 0").groupBy(F.col("tissue").alias("lang")).agg(F.count_distinct("class").alias("classes"))


@query(
    "cluster_profile",
    f"WITH {TILES}, q AS (SELECT lang, {_COHORT} AS cohort, length(content) AS len FROM t) SELECT lang AS node, count(*) AS n, CASE WHEN avg(CASE WHEN cohort = 'B' THEN 1.0 ELSE 0.0 END) > 0.5 THEN 'B' ELSE 'A' END AS main_cohort, round(avg(len), 6) AS len FROM q GROUP BY lang",
)
def _(spark, sf):
    s = slides(spark, sf).select("slide_id", "cohort", "tissue")
    rows = doc_tiles(spark, sf).select("slide_id", F.length("content").alias("len")).join(s, "slide_id")
    p = metrics.profile_clusters(rows.withColumnRenamed("tissue", "node"), "node", ["len"])
    return p.select("node", "n", "main_cohort", r("len").alias("len"))


_RESULTS = "res AS (SELECT source AS setting, lang AS task, avg(n_chars) AS mean FROM documents GROUP BY ALL)"


def results(spark, sf):
    return table(spark, sf, "documents").groupBy(F.col("source").alias("setting"), F.col("lang").alias("task")).agg(F.avg("n_chars").alias("mean"))


@query("rank_settings", f"WITH {_RESULTS} SELECT setting, task, CAST(dense_rank() OVER (PARTITION BY task ORDER BY mean DESC) AS INTEGER) AS place FROM res")
def _(spark, sf):
    return metrics.rank_settings(results(spark, sf)).select("setting", "task", "place")


@query("corr_share_metric", f"WITH {_RESULTS}, s AS (SELECT source AS setting, lang AS task, count(*) AS n FROM documents GROUP BY ALL) SELECT round(corr(mean, n), 6) AS corr FROM res JOIN s USING (setting, task)")
def _(spark, sf):
    s = table(spark, sf, "documents").groupBy(F.col("source").alias("setting"), F.col("lang").alias("task")).agg(F.count("*").alias("share"))
    return metrics.share_score_corr(results(spark, sf), s, ["setting", "task"]).select(r("corr").alias("corr"))


@query("summarise_results", f"WITH {_RESULTS} SELECT setting, task AS family, round(avg(mean), 6) AS mean FROM res GROUP BY GROUPING SETS ((setting), (setting, task))")
def _(spark, sf):
    return metrics.summarise(results(spark, sf).withColumnRenamed("task", "family")).select("setting", "family", r("mean").alias("mean"))


@query("select_uncertain", "SELECT doc_id AS id FROM (SELECT doc_id, least(n_chars / 5000.0::DOUBLE, 1.0::DOUBLE) AS score FROM documents) s ORDER BY abs(score - 0.5::DOUBLE), doc_id LIMIT 50")
def _(spark, sf):
    s = table(spark, sf, "documents").select(F.col("doc_id").alias("id"), F.least(F.col("n_chars") / 5000.0, F.lit(1.0)).alias("score"))
    return allocate.select_uncertain(s, 50).select("id")


# Batches ----------------------------------------------------------------------------------------------------

_SUB = "s AS (SELECT doc_id AS point_id, lang AS cluster FROM documents)"


def small_subset(spark, sf):
    return table(spark, sf, "documents").select(F.col("doc_id").alias("point_id"), "lang", "source")


@query(
    "batches_shuffled",
    "WITH e AS (SELECT doc_id AS point_id, epoch FROM documents, unnest(range(0, 4)) AS u(epoch)), o AS (SELECT *, row_number() OVER (ORDER BY epoch, md5(concat('17:', epoch, ':', point_id)), point_id) - 1 AS ordinal FROM e) SELECT ordinal // 16 AS iteration, CAST(ordinal % 16 AS INTEGER) AS slot, point_id FROM o WHERE ordinal < 16 * 120 AND ordinal < 4 * (SELECT count(*) FROM documents)",
)
def _(spark, sf):
    return batching.plan_shuffled(small_subset(spark, sf), 16, 120)


def _strat_sql(col, b, t):
    return (
        f"WITH s AS (SELECT doc_id AS point_id, {col} AS cluster FROM documents), z AS (SELECT cluster, count(*) AS s, row_number() OVER (ORDER BY cluster) - 1 AS o, count(*) OVER () AS k FROM s GROUP BY cluster), "
        # slots are dealt one by one: the first q * k of a batch in turn, the rest go on round all clusters
        f"g AS (SELECT t, e, CASE WHEN e < ({b} // k) * k THEN e % k ELSE (t * ({b} % k) + e - ({b} // k) * k) % k END AS o FROM unnest(range(0, {t})) AS u(t), unnest(range(0, {b})) AS w(e), (SELECT any_value(k) AS k FROM z)), "
        "j AS (SELECT t, o, row_number() OVER (PARTITION BY o ORDER BY t, e) - 1 AS j FROM g), p AS (SELECT cluster, point_id, pass, row_number() OVER (PARTITION BY cluster, pass ORDER BY md5(concat('17:', pass, ':', point_id)), point_id) - 1 AS place FROM s, unnest(range(0, 40)) AS u(pass)) "
        "SELECT t AS iteration, z.cluster, p.point_id, j.j // z.s AS seen_before FROM j JOIN z USING (o) JOIN p ON p.cluster = z.cluster AND p.pass = j.j // z.s AND p.place = j.j % z.s"
    )


for _name, _col, _b in (("batches_stratified", "lang", 15), ("batches_by_label", "source", 20), ("batches_by_lower_level", "concat(lang, ':', source)", 96)):
    def _plan(spark, sf, col=_col, b=_b):
        s = small_subset(spark, sf).withColumn("cluster", F.expr(col))
        return batching.plan_stratified(s, "cluster", b, 30).select("iteration", "cluster", "point_id", "seen_before")

    query(_name, _strat_sql(_col, _b, 30))(_plan)


@query(
    "batch_audit",
    f"WITH p AS ({_strat_sql('lang', 15, 30)}), b AS (SELECT cluster, iteration, count(*) AS n FROM p GROUP BY ALL), v AS (SELECT cluster, point_id, count(*) AS v FROM p GROUP BY ALL) SELECT cluster, draws, lb AS least_per_batch, mb AS most_per_batch, lv AS least_views, mv AS most_views FROM (SELECT cluster, CAST(sum(n) AS BIGINT) AS draws, min(n) AS lb, max(n) AS mb FROM b GROUP BY 1) x JOIN (SELECT cluster, min(v) AS lv, max(v) AS mv FROM v GROUP BY 1) y USING (cluster)",
)
def _(spark, sf):
    return batching.audit_plan(batching.plan_stratified(small_subset(spark, sf), "lang", 15, 30)).drop("tiles_seen")


@query("batch_tv", f"WITH p AS ({_strat_sql('lang', 15, 30)}), n AS (SELECT iteration, cluster, count(*)::DOUBLE / 15 AS p FROM p GROUP BY ALL), x AS (SELECT iteration, sum(abs(p - 0.25)) / 2 AS tv FROM n GROUP BY 1) SELECT round(avg(tv), 8) AS mean_tv, round(max(tv), 8) AS max_tv FROM x")
def _(spark, sf):
    b = batching.batch_tv(batching.plan_stratified(small_subset(spark, sf), "lang", 15, 30), 4)
    return b.select(r("mean_tv", 8).alias("mean_tv"), r("max_tv", 8).alias("max_tv"))


# Trees, settings and learners (checked by invariants in tests) ------------------------------------------------


def tile_points(spark, sf):
    return features.hash_embed(detect_regions(doc_tiles(spark, sf)))


def packed_points(spark, sf):
    """tile_points, written once as counts and unpacked at each pass."""
    return features.unpacked(staged(spread(features.packed_embed(detect_regions(doc_tiles(spark, sf))))))


def built(spark, sf, shape):
    return tree.build_tree(packed_points(spark, sf), lambda n: tree.level_counts(n, shape=shape), resample_rounds=1, stage=False)


def both_built(spark, sf):
    """(shape, tree) of both shapes. Their leaves are the same clusters of the same points, fit once."""
    points, leaves = packed_points(spark, sf), {}
    n = points.count()
    for shape in ("narrow", "wide"):
        counts = tree.level_counts(n, shape=shape)
        if n and counts[0] not in leaves:
            leaves[counts[0]] = tree.fit_level(points, counts[0], resample_rounds=1)
        yield shape, tree.build_tree(points, counts, resample_rounds=1, stage=False, leaves=leaves.get(counts[0]))


def paths_of(t):
    return t.paths().select("point_id", *[f"c{i}" for i in range(t.depth, 0, -1)])


for _shape in ("narrow", "wide"):
    query(f"tree_full_{_shape}")(lambda spark, sf, s=_shape: built(spark, sf, s).nodes(centroids=False))


@query("balance_curve_trees")
def _(spark, sf):
    """Distance from uniform at levels 4 and 3, for both trees, both start levels and a grid of fractions."""
    out = []
    for shape, t in both_built(spark, sf):
        leaves = staged(paths_of(t).groupBy("c4", "c3", "c2", "c1").agg(F.count("*").alias("size")))
        n = leaves.agg(F.sum("size")).first()[0]
        runs = spark.createDataFrame([(f, int(round(n * f / 100))) for f in (1, 2, 5, 10, 20, 40, 100)], "run int, budget long")
        base = leaves.crossJoin(F.broadcast(runs))
        for start in (4, 3):
            levels = [f"c{i}" for i in range(start, 0, -1)]
            g = allocate.allocate_tree(base, levels, "budget", keys=["run"])["c1"].select("run", "c1", "granted")
            g = staged(g.join(t.path_table(), "c1"))
            for level in (4, 3):
                c = g.groupBy("run", f"c{level}").agg(F.sum("granted").alias("n"))
                tv = metrics.tv_uniform(c, c, [f"c{level}"], by=["run"])
                out.append(tv.select(F.lit(shape).alias("tree"), F.lit(start).alias("start_level"), F.lit(level).alias("level"), "run", "tv"))
    total = out[0]
    for x in out[1:]:
        total = total.unionByName(x)
    return total


@query("layout_top_nodes")
def _(spark, sf):
    t = built(spark, sf, "narrow")
    y = projection.layout_2d(t.centroids[-1])
    xy = spark.createDataFrame([(i, float(a), float(b)) for i, (a, b) in enumerate(y)], "node long, x double, y double")
    sub = allocate.curate(paths_of(t), ["c4", "c3", "c2", "c1"], fraction=0.1)
    a = t.sizes(4).select("node", F.col("log_n").alias("log_pool"))
    return xy.join(a, "node").join(t.sizes(4, sub).select("node", F.col("log_n").alias("log_subset")), "node")


@query("feature_cluster_ari")
def _(spark, sf):
    """Clusters of hand-made features, all and by group, laid out in two dimensions, against tree levels 4 and 3.
    The control (labels by hash) shows what chance gives."""
    t = built(spark, sf, "narrow")
    paths, k = staged(t.paths()), t.counts[-1]
    f = staged(features.handmade_features(detect_regions(doc_tiles(spark, sf))))
    groups, out = {"all": features.GROUPS, **{g: {g: cs} for g, cs in features.GROUPS.items()}}, None
    for name, held in groups.items():
        flat = f.select("tile_id", *[F.col(f"{g}.{c}").alias(c) for g, cs in held.items() for c in cs])
        p = staged(projection.neighbour_layout(features.vectorise(flat, "tile_id", flat.columns[1:]), epochs=60))
        of = kmeans.assign(p, kmeans.kmeans_fit(p, k, max_iter=5).centroids).select("point_id", F.col("node").alias("f"))
        both = paths.join(of, "point_id")
        tries = [(name, both)] + ([("control", both.withColumn("f", F.pmod(F.xxhash64("point_id"), F.lit(k))))] if name == "all" else [])
        for label, rows in tries:
            for level in (4, 3):
                one = metrics.adjusted_rand(rows, "f", f"c{level}").select(F.lit(label).alias("features"), F.lit(level).alias("level"), "ari")
                out = one if out is None else out.unionByName(one)
    return out


@query("composition_of_subsets")
def _(spark, sf):
    """Share of each tissue and of cohort B inside it, and classes touched: pool, label-balanced and tree subset."""
    info = slides(spark, sf)
    label = class_label(info).select("slide_id", "class", "cohort", "tissue")
    pool = staged(tile_paths(spark, sf).select("point_id", "slide_id").join(label, "slide_id"))
    ids = paths_of(built(spark, sf, "narrow"))
    subsets = {
        "full": pool, "label": allocate.curate_even(pool, "class", pool.count() // 10),
        "narrow": pool.join(allocate.curate(ids, ["c4", "c3", "c2", "c1"], fraction=0.1).select("point_id"), "point_id", "left_semi"),
    }
    out = None
    for name, sub in subsets.items():
        one = metrics.composition(sub, "tissue", classes="class").withColumn("subset", F.lit(name))
        out = one if out is None else out.unionByName(one)
    return out


@query("kmeans_lineitem_scale")
def _(spark, sf):
    """Numeric rows at scale: K-means and node sizes."""
    cols = ["l_quantity", "l_extendedprice", "l_discount", "l_tax"]
    rows = table(spark, sf, "lineitem").withColumn("rid", F.xxhash64("l_orderkey", "l_linenumber", *cols))
    p = features.vectorise(rows, "rid", cols)
    m = kmeans.kmeans_fit(p, 32, init="random", max_iter=5)
    return kmeans.assign(p, m.centroids).groupBy("node").agg(F.count("*").alias("n"), F.sum("dist2").alias("sse"))
