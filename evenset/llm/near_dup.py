"""Near-duplicate groups by bottom-k sketches from one hash function.

Every text becomes the set of its distinct word shingles, each one 64-bit hash. Texts with equal sets form a
class, and only the class with its least id goes on. The least `index_k` values of a class are posted to
inverted lists; sharing a list makes a candidate, the estimate from the union of two bottom-`sketch_k`
sketches filters it, and the exact Jaccard similarity of the full sets confirms it. Components of the
confirmed links give the groups.

A list that holds more than `hot` classes is mostly a passage that unlike documents share. A class of whose values
at most a quarter are hot meets its partners in the other lists and skips the hot ones. Any other class posts its
least `deep_k` values, and skips its hot lists too if at least `deep_rare` of those are rare; what is left (texts
that consist mostly of shared passages) stays in its hot lists. Inside a list, classes that are surely alike
(estimate `sure` standard errors above the threshold) are chained by spanning links instead of all pairs; pairs
within four errors of it are confirmed if no chain joins them. A pair is settled in the first list that it shares.
Should a link of a chain fail when it is confirmed, the lists that hold both its ends are gone through again
without it, until every chain holds. Lists beyond `list_rows` are cut into sub-lists, and every pair of sub-lists is
compared, so no link is lost to a cap.

What can be missed: a pair at the threshold shares none of its least 16 values with probability 0.25**16; if a
quarter of the values are hot and skipped, none of the other 12 with (1/3)**12 (2e-6), and if half of them are, none
of 32 deep ones with 0.5**32; an estimate lies four errors low with 3e-5.

Defined cases: texts without words have an empty set and stay alone; texts shorter than a shingle are one
shingle; a null id links with nothing, its component is null and it is kept; rows with equal ids are one node,
linked with whatever any of their texts is linked with.
"""

from __future__ import annotations

from collections.abc import Iterator

import numpy as np
import pandas as pd
import xxhash
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from .shared import join_weighted, keep_table, read_table, spare_name

SKETCH = 128
_MULT = np.uint64(0x9E3779B97F4A7C15)
_MIX = np.uint64(0xBF58476D1CE4E5B9)


def shingle_set(text: str | None, width: int, memo: dict[bytes, int]) -> np.ndarray:
    """Sorted distinct 64-bit hashes of the word shingles."""
    words = (text or "").encode("utf-8", "surrogatepass").lower().split()
    if not words:
        return np.zeros(0, np.uint64)
    if len(memo) > 400_000:
        memo.clear()
    ids = []
    for w in words:
        h = memo.get(w)
        if h is None:
            h = memo[w] = xxhash.xxh64_intdigest(w)
        ids.append(h)
    a = np.array(ids, np.uint64)
    span = min(width, len(a))
    h = a[: len(a) - span + 1] + np.uint64(span)
    for i in range(1, span):
        h = h * _MULT + a[i : len(a) - span + 1 + i]
        h ^= h >> np.uint64(29)
    h = h * _MIX
    h ^= h >> np.uint64(32)
    return np.unique(h)


def list_links(
    ids: np.ndarray,
    sizes: np.ndarray,
    sketches: list[np.ndarray],
    threshold: float,
    side: np.ndarray | None = None,
    earlier: list[np.ndarray] | None = None,
    broken: list[tuple[int, int]] = (),
    sure: float = 4.0,
) -> tuple[np.ndarray, np.ndarray, np.ndarray]:
    """Candidate links (a, b, of a chain) inside one list: spanning links of the surely alike and all unsure pairs
    across them. side: two sub-lists by 0 and 1, of which only pairs across are asked; None asks all.
    earlier: per class, its lists that come before this one; pairs that meet there are settled there.
    broken: pairs known to be unlike."""
    order = np.argsort(ids, kind="stable")
    ids, sizes, sketches = ids[order], sizes[order], [sketches[i] for i in order]
    side = None if side is None else side[order]
    m = len(ids)
    none = np.zeros(0, np.int64)
    if m < 2:
        return none, none, np.zeros(0, bool)
    place: dict[int, list[int]] = {}
    for i, x in enumerate(ids.tolist()):
        place.setdefault(x, []).append(i)
    unlike = [(i, j) for a, b in broken for i in place.get(a, ()) for j in place.get(b, ())]
    counts = np.array([len(s) for s in sketches])
    seen = _incidence(sketches)
    met = None if earlier is None else _incidence([earlier[i] for i in order])
    # a sketch that holds its whole set has no end
    whole = sizes <= counts
    tops = np.where(whole, np.iinfo(np.int64).max, [int(s[-1]) for s in sketches]).astype(np.int64)
    ends = tops.clip(max=2**32 - 1).astype(np.uint32)
    ranks = np.stack([np.searchsorted(s, ends, "right") for s in sketches]).astype(np.int32)
    label = np.arange(m)
    links: list[tuple[int, int]] = []
    unsure: list[tuple[np.ndarray, np.ndarray]] = []
    step = max(1, (1 << 20) // m)
    for at in range(0, m, step):
        rows = slice(at, min(m, at + step))
        common = seen[rows] @ seen.T
        # the union of both sketches, up to the lesser of their ends, is a sample of the union of the sets
        lower = tops[rows, None] <= tops[None, :]
        union = np.where(lower, counts[rows, None], ranks[rows])
        union = np.maximum(union + np.where(lower, ranks.T[rows], counts[None, :]) - common, 1)
        est = common / union
        rare = (sizes[rows, None] < threshold * sizes[None, :]) | (sizes[None, :] < threshold * sizes[rows, None])
        est[rare] = 0
        every = (sizes[rows, None] + sizes[None, :]) / (1 + threshold)
        error = np.sqrt(threshold * (1 - threshold) / union * np.clip(1 - union / every, 0, 1))
        error[whole[rows, None] & whole[None, :]] = 0
        high = est >= threshold + sure * error
        maybe = (est >= threshold - 4 * error - 1e-6) & ~high
        for i, j in unlike:
            for x, y in ((i, j), (j, i)):
                if at <= x < rows.stop:
                    high[x - at, y] = maybe[x - at, y] = False
        elsewhere = None if met is None else (met[rows] @ met.T) > 0
        for i in range(rows.start, rows.stop):
            js = i + 1 + np.flatnonzero(high[i - at, i + 1 :])
            us = i + 1 + np.flatnonzero(maybe[i - at, i + 1 :])
            if side is not None:
                js, us = js[side[js] != side[i]], us[side[us] != side[i]]
            js = js[label[js] != label[i]]
            while len(js):
                j = int(js[0])
                if elsewhere is None or not elsewhere[i - at, j]:
                    links.append((i, j))
                label[label == label[j]] = label[i]
                js = js[label[js] != label[i]]
            us = us[label[us] != label[i]]
            if elsewhere is not None:
                us = us[~elsewhere[i - at, us]]
            if len(us):
                unsure.append((np.full(len(us), i), us))
    a = np.concatenate([np.array([x for x, _ in links], np.int64), *[x for x, _ in unsure]])
    b = np.concatenate([np.array([y for _, y in links], np.int64), *[y for _, y in unsure]])
    keep = np.ones(len(a), bool)
    keep[len(links) :] = label[a[len(links) :]] != label[b[len(links) :]]
    return ids[a[keep]], ids[b[keep]], np.arange(len(a))[keep] < len(links)


def _incidence(sets: list[np.ndarray]) -> np.ndarray:
    """0/1 matrix of sets by the values that at least two of them hold."""
    flat = np.concatenate(sets)
    owner = np.repeat(np.arange(len(sets)), [len(s) for s in sets])
    _, code, held = np.unique(flat, return_inverse=True, return_counts=True)
    shared = held > 1
    place = np.cumsum(shared) - 1
    use = shared[code]
    out = np.zeros((len(sets), int(shared.sum())), np.float32)
    out[owner[use], place[code[use]]] = 1
    return out


def _profiles(width: int, index_k: int, deep_k: int, sketch_k: int):
    def run(batches: Iterator[pd.DataFrame]) -> Iterator[pd.DataFrame]:
        memo: dict[bytes, int] = {}
        for pdf in batches:
            for at in range(0, len(pdf), 2000):
                part = pdf.iloc[at : at + 2000]
                sets = [shingle_set(t, width, memo) for t in part["text"]]
                yield pd.DataFrame(
                    {
                        "doc_id": part["doc_id"],
                        "n_shingles": [len(s) for s in sets],
                        "digest": [xxhash.xxh128_hexdigest(s.tobytes()) for s in sets],
                        "keys": [s[:index_k].view(np.int64) for s in sets],
                        "more": [s[index_k:deep_k].view(np.int64) for s in sets],
                        "sketch": [(s[:sketch_k] >> np.uint64(32)).astype(np.uint32).tobytes() for s in sets],
                    }
                )

    return run


def _lists(threshold: float, sure: float):
    def run(batches: Iterator[pd.DataFrame]) -> Iterator[pd.DataFrame]:
        held: list[pd.DataFrame] = []
        now = None

        def flush() -> pd.DataFrame:
            pdf = pd.concat(held) if len(held) > 1 else held[0]
            cells = pdf["cell"].to_numpy()
            sketches = [np.frombuffer(x, np.uint32) for x in pdf["sketch"]]
            side = cells if (cells >= 0).any() else None
            here = pdf["v"].iloc[0]
            earlier = [x[x < here] for x in (np.asarray(x, np.int64) for x in pdf["mine"])]
            broken = [(int(x["a"]), int(x["b"])) for x in pdf["broken"].iloc[0]] if "broken" in pdf else []
            ids, sizes = pdf["id"].to_numpy(np.int64), pdf["n"].to_numpy(np.int64)
            a, b, chain = list_links(ids, sizes, sketches, threshold, side, earlier, broken, sure)
            return pd.DataFrame({"a": a, "b": b, "chain": chain})

        for pdf in batches:
            v, lo, hi = (pdf[c].to_numpy() for c in ("v", "lo", "hi"))
            cuts = np.flatnonzero((v[1:] != v[:-1]) | (lo[1:] != lo[:-1]) | (hi[1:] != hi[:-1])) + 1
            out = []
            for at, to in zip([0, *cuts], [*cuts, len(pdf)]):
                key = (v[at], lo[at], hi[at])
                if held and key != now:
                    out.append(flush())
                    held = []
                now = key
                held.append(pdf.iloc[at:to])
            out = [x for x in out if len(x)]
            if out:
                yield pd.concat(out)
        if held:
            yield flush()

    return run


def _confirm(width: int, percent: int):
    def run(batches: Iterator[pd.DataFrame]) -> Iterator[pd.DataFrame]:
        memo: dict[bytes, int] = {}
        last, left = None, None
        for pdf in batches:
            good = []
            for ta, tb in zip(pdf["text_a"], pdf["text_b"]):
                if ta != last:
                    last, left = ta, shingle_set(ta, width, memo)
                right = shingle_set(tb, width, memo)
                both = len(np.intersect1d(left, right, assume_unique=True))
                good.append(bool(both) and 100 * both >= percent * (len(left) + len(right) - both))
            yield pd.DataFrame({"a": pdf["a"], "b": pdf["b"], "chain": pdf["chain"], "ok": np.array(good, bool)})

    return run


def components(edges: DataFrame) -> DataFrame:
    """(node, root) for every node of the edges (a, b); root: the least node reachable.

    Each round hangs every node below its least neighbour, shortens all ways up by pointer jumping until they end
    at a root, and contracts the edges. A round leaves at most half of the nodes that still have edges, and
    jumps double the way, so both counts grow with the logarithm of the component, whatever the order of ids."""
    spark = edges.sparkSession
    edges = edges.where("a <> b").select(F.least("a", "b").alias("a"), F.greatest("a", "b").alias("b"))
    edges = keep_table(edges.distinct(), "edges")
    steps: list[DataFrame] = []
    while total := edges.count():
        both = edges.union(edges.select(F.col("b"), F.col("a")).toDF("a", "b"))
        hung = both.groupBy("a").agg(F.least("a", F.min("b")).alias("up"))
        up = keep_table(hung.withColumnRenamed("a", "node"), "up")
        while True:
            kids = up.groupBy("up").agg(F.count("*").alias("kids")).withColumnRenamed("up", "at")
            above = up.join(kids, up["node"] == kids["at"]).select("at", "kids", F.col("up").alias("next"))
            moved = join_weighted(up.withColumnRenamed("up", "at"), above, ["at"], "kids", 2 * total)
            moved = keep_table(moved.select("node", "at", F.col("next").alias("up")), "up")
            up = moved.drop("at")
            if not moved.where("up <> at").take(1):
                break
        steps.append(up)
        held = both.groupBy("a").agg(F.count("*").alias("n")).withColumnRenamed("a", "node")
        roots = keep_table(up.join(held, "node"), "roots")
        near = join_weighted(edges.withColumnRenamed("a", "node"), roots, ["node"], "n", 2 * total).select(F.col("up").alias("x"), F.col("b").alias("node"))
        far = join_weighted(near, roots, ["node"], "n", 2 * total).select("x", F.col("up").alias("y"))
        far = far.where("x <> y").select(F.least("x", "y").alias("a"), F.greatest("x", "y").alias("b"))
        edges = keep_table(far.distinct(), "edges")
    if not steps:
        return spark.createDataFrame([], "node long, root long")
    out = steps[0].select("node", F.col("up").alias("root"))
    for up in steps[1:]:
        step = up.select(F.col("node").alias("at"), "up")
        out = out.join(step, F.col("root") == F.col("at"), "left").select("node", F.coalesce("up", "root").alias("root"))
    return out


def _deal(pairs: DataFrame, side: str, total: int, per_task: int = 2000) -> tuple[DataFrame, DataFrame]:
    """(pairs + copy_<side>, copies wanted per id of that side). A text that over per_task pairs ask for is copied,
    one copy for so many, so that no task gets all pairs of one text."""
    wanted = pairs.groupBy(side).agg(F.count("*").alias("n")).withColumn("copies", F.ceil(F.col("n") / per_task).cast("int"))
    wanted = keep_table(wanted, "wanted")
    other = "b" if side == "a" else "a"
    dealt = join_weighted(pairs, wanted, [side], "n", total)
    dealt = dealt.withColumn(f"copy_{side}", F.pmod(F.xxhash64(other), F.col("copies")).cast("int")).drop("n", "copies")
    return dealt, wanted.withColumn(f"copy_{side}", F.explode(F.sequence(F.lit(0), F.col("copies") - 1))).drop("n", "copies")


def near_duplicates(
    docs: DataFrame,
    *,
    id_col: str = "doc_id",
    text_col: str = "text",
    width: int = 5,
    percent: int = 75,
    index_k: int = 16,
    sketch_k: int = SKETCH,
    hot: int = 256,
    deep_k: int = 64,
    deep_rare: int = 32,
    list_rows: int = 3000,
    sure: float = 4.0,
) -> DataFrame:
    """doc_id, n_shingles, component_id, kept for every row."""
    if 100 * deep_rare <= (100 - percent) * deep_k:
        raise ValueError("texts could be alike by hot values alone: raise deep_rare")
    src = docs.select(F.col(id_col).cast("long").alias("doc_id"), F.col(text_col).alias("text"))
    known = src.where("doc_id is not null")
    schema = "doc_id long, n_shingles long, digest string, keys array<long>, more array<long>, sketch binary"
    parts = keep_table(known.mapInPandas(_profiles(width, index_k, deep_k, sketch_k), schema), "sketches")
    classes = keep_table(
        parts.where("n_shingles > 0").groupBy("digest").agg(F.min("doc_id").alias("class_id")), "classes"
    )
    lead = classes.withColumnRenamed("class_id", "doc_id")

    def heads(*columns: str) -> DataFrame:
        held = parts.join(lead, ["digest", "doc_id"], "left_semi").dropDuplicates(["digest", "doc_id"])
        return held.select(F.col("doc_id").alias("id"), "digest", *columns)

    size = F.size("keys")
    least = heads("keys").select("id", "digest", size.alias("posted"), F.lit(False).alias("deep"), F.explode("keys").alias("v"))
    crowded = least.groupBy("v").agg(F.count("*").alias("m")).where(F.col("m") > hot).select("v")
    laden = least.join(crowded, "v").groupBy("id", "digest", "posted").agg(F.count("*").alias("crowd"))
    # with at least three quarters of its values rare, a class meets its partners in their lists
    laden = keep_table(laden.where(4 * F.col("crowd") > F.col("posted")).select("id", "digest", "posted"), "laden")
    more = heads("more").join(laden, ["id", "digest"])
    more = more.select("id", "digest", (F.col("posted") + F.size("more")).alias("posted"), F.lit(True).alias("deep"), F.explode("more").alias("v"))
    posts = least.unionByName(more)
    lengths = posts.groupBy("v").agg(F.count("*").alias("m")).where("m > 1")
    per_class = (
        posts.join(lengths, "v")
        .groupBy("id", "digest")
        .agg(F.max("deep").alias("deep"), F.max("posted").alias("posted"), F.collect_list(F.struct("v", "m")).alias("lists"))
    )
    n_hot = F.size(F.filter("lists", lambda x: x["m"] > hot))
    covered = F.when(F.col("deep"), F.col("posted") - n_hot >= deep_rare).otherwise(4 * n_hot <= F.col("posted"))
    lists = F.when(covered, F.filter("lists", lambda x: x["m"] <= hot)).otherwise(F.col("lists"))
    per_class = keep_table(per_class.select("id", "digest", lists.alias("lists")).where(F.size("lists") > 0), "lists")
    entries = (
        heads("n_shingles", "sketch")
        .join(per_class, ["id", "digest"])
        .select("id", F.col("n_shingles").alias("n"), "sketch", F.col("lists.v").alias("mine"), F.explode("lists").alias("x"))
        .select("id", "n", "sketch", "mine", "x.v", "x.m")
    )

    def search(entries: DataFrame, more: list[str]) -> DataFrame:
        subs = F.greatest(F.lit(1), F.ceil(F.col("m") / list_rows)).cast("int")
        own = F.pmod(F.xxhash64("id", "v"), subs).cast("int")
        # every pair of sub-lists is a cell; (s, s) compares within, (s, t) across
        cell = F.when(F.col("own") == F.col("other"), -1).otherwise((F.col("own") > F.col("other")).cast("int"))
        celled = (
            entries.withColumn("own", own)
            .withColumn("other", F.explode(F.sequence(F.lit(0), subs - 1)))
            .withColumn("cell", cell)
            .withColumn("lo", F.least("own", "other"))
            .withColumn("hi", F.greatest("own", "other"))
            .select("v", "lo", "hi", "cell", "id", "n", "sketch", "mine", *more)
        )
        found = (
            celled.repartition("v", "lo", "hi")
            .sortWithinPartitions("v", "lo", "hi")
            .mapInPandas(_lists(percent / 100, sure), "a long, b long, chain boolean")
        )
        return found.where("a <> b").groupBy("a", "b").agg(F.max("chain").alias("chain"))

    texts = known.where("text is not null")

    def confirm(pairs: DataFrame) -> DataFrame:
        pairs = keep_table(pairs, "candidates")
        total = pairs.count()
        dealt, of_a = _deal(pairs, "a", total)
        dealt, of_b = _deal(dealt, "b", total)
        text = lambda side, held: texts.select(F.col("doc_id").alias(side), F.col("text").alias(f"text_{side}")).join(held, side)
        sided = dealt.join(text("b", of_b), ["b", "copy_b"]).join(text("a", of_a), ["a", "copy_a"])
        each = sided.mapInPandas(_confirm(width, percent), "a long, b long, chain boolean, ok boolean")
        return keep_table(each.groupBy("a", "b").agg(F.max("chain").alias("chain"), F.max("ok").alias("ok")), "confirmed")

    checked = fresh = confirm(search(entries, []))
    while fresh.where("chain and not ok").take(1):
        broken = checked.where("chain and not ok").select("a", "b")
        lists_of = lambda c: per_class.select(F.col("id").alias(c), F.explode("lists.v").alias("v"))
        again = broken.join(lists_of("a"), "a").join(lists_of("b"), ["b", "v"])
        again = again.groupBy("v").agg(F.collect_set(F.struct("a", "b")).alias("broken"))
        redone = search(entries.join(keep_table(again, "broken"), "v"), ["broken"])
        fresh = confirm(redone.join(checked, ["a", "b"], "left_anti"))
        checked = checked.unionByName(fresh)
    # texts of one id are one node
    several = parts.groupBy("doc_id").agg(F.count_distinct("digest").alias("n")).where("n > 1").select("doc_id")
    tied = parts.join(several, "doc_id", "left_semi").join(classes, "digest").select(F.col("doc_id").alias("a"), F.col("class_id").alias("b"))
    roots = components(checked.where("ok").select("a", "b").unionByName(tied))
    out = (
        parts.select("doc_id", "n_shingles", "digest")
        .join(classes, "digest", "left")
        .withColumn("node", F.coalesce("class_id", "doc_id"))
        .join(roots, "node", "left")
        .select("doc_id", "n_shingles", F.coalesce("root", "node").alias("component_id"))
    )
    lone = src.where("doc_id is null").mapInPandas(_profiles(width, 1, 1, 1), schema)
    lone = lone.select("doc_id", "n_shingles", F.lit(None).cast("long").alias("component_id"))
    return out.unionByName(lone).withColumn(
        "kept", F.coalesce(F.col("doc_id") == F.col("component_id"), F.lit(True))
    )


def drop_near_duplicates(docs: DataFrame, **options) -> DataFrame:
    """One document of each group, columns unchanged."""
    name, id_col = spare_name(docs, "gone"), options.get("id_col", "doc_id")
    gone = near_duplicates(docs, **options).where("not kept").select(F.col("doc_id").alias(name)).distinct()
    return docs.join(gone, F.col(id_col) == F.col(name), "left_anti")


def op9_near_duplicates(spark: SparkSession, sf_dir: str) -> DataFrame:
    return near_duplicates(read_table(spark, sf_dir, "documents"))


# The same by plain counting: all shingles that two texts share, then all ways along the links.
OP9_SQL = r"""
WITH RECURSIVE w AS (SELECT doc_id, regexp_extract_all(translate(coalesce(text, ''), 'ABCDEFGHIJKLMNOPQRSTUVWXYZ', 'abcdefghijklmnopqrstuvwxyz'), '[^\x20\x09-\x0D]+') AS ws FROM documents),
s AS (SELECT DISTINCT doc_id, unnest(CASE WHEN len(ws) = 0 THEN [] WHEN len(ws) < 5 THEN [array_to_string(ws, ' ')]
  ELSE [array_to_string(ws[i:i + 4], ' ') FOR i IN range(1, len(ws) - 3)] END) AS g FROM w),
n AS (SELECT doc_id, count(*) AS n FROM s GROUP BY doc_id),
met AS (SELECT a.doc_id AS x, b.doc_id AS y, count(*) AS m FROM s a JOIN s b ON a.g = b.g AND a.doc_id < b.doc_id GROUP BY ALL),
l AS (SELECT x, y FROM met JOIN n p ON x = p.doc_id JOIN n q ON y = q.doc_id WHERE 100 * m >= 75 * (p.n + q.n - m)),
e AS (SELECT x, y FROM l UNION SELECT y, x FROM l),
r AS (SELECT doc_id, doc_id AS c FROM documents UNION SELECT r.doc_id, e.y FROM r JOIN e ON r.c = e.x),
k AS (SELECT doc_id, min(c) AS component_id FROM r GROUP BY doc_id)
SELECT d.doc_id, coalesce(n.n, 0) AS n_shingles, k.component_id, d.doc_id = k.component_id AS kept
FROM documents d JOIN k ON d.doc_id = k.doc_id LEFT JOIN n ON d.doc_id = n.doc_id
"""
