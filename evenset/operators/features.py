"""Base vectors, hand-made features and linear projections."""

from __future__ import annotations

import numpy as np
import pandas as pd
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from ..functions.linalg import norm, to_matrix


def bigram_counts(text: str, d: int) -> np.ndarray:
    code = np.frombuffer(text.lower().encode("utf-32-le", "surrogatepass"), np.uint32).astype(np.int64)
    return np.bincount((31 * code[:-1] + code[1:]) % d, minlength=d) if len(code) > 1 else np.zeros(d, np.int64)


def bigram_cells(tiles: DataFrame, d: int = 64) -> DataFrame:
    """Long form: tile_id, bucket, n of every bucket that occurs. Built-in functions only."""
    t = F.lower("content")
    rows = tiles.where(F.length("content") > 1).select(
        "tile_id", t.alias("t"), F.explode(F.sequence(F.lit(1), F.length(t) - 1)).alias("i")
    )
    one = lambda at: F.expr(f"ascii(substring(t, {at}, 1))")
    return rows.groupBy("tile_id", ((31 * one("i") + one("i + 1")) % d).alias("bucket")).agg(F.count("*").alias("n"))


def hash_embed(tiles: DataFrame, d: int = 64) -> DataFrame:
    """point_id, vec: hashed bigram counts at unit length, one Arrow pass."""

    @F.pandas_udf("array<double>")
    def embed(content: pd.Series) -> pd.Series:
        out = []
        for t in content:
            v = bigram_counts(t or "", d).astype(float)
            out.append(v / (np.linalg.norm(v) or 1.0))
        return pd.Series(out, dtype=object)

    return tiles.select(F.col("tile_id").alias("point_id"), embed("content").alias("vec"))


def packed_embed(tiles: DataFrame, d: int = 64) -> DataFrame:
    """point_id, n, size: the counts behind hash_embed's vectors and their length. Written out, they take about a
    tenth of the bytes; unpacked() gives the vectors, equal to the last bit."""

    def run(batches):
        for b in batches:
            n = np.array([bigram_counts(t or "", d) for t in b.column("content").to_pylist()], np.int32).reshape(-1, d)
            size = np.sqrt((n.astype(float) ** 2).sum(axis=1))
            lists = pa.ListArray.from_arrays(np.arange(len(n) + 1, dtype=np.int32) * d, pa.array(n.ravel()))
            yield pa.record_batch([b.column("point_id"), lists, pa.array(np.where(size > 0, size, 1.0))], ["point_id", "n", "size"])

    rows = tiles.select(F.col("tile_id").cast("long").alias("point_id"), "content")
    return rows.mapInArrow(run, "point_id long, n array<int>, size double")


def unpacked(packed: DataFrame) -> DataFrame:
    vec = F.transform("n", lambda x: x / F.col("size"))
    return packed.select("point_id", F.coalesce(vec, F.array().cast("array<double>")).alias("vec"))  # never null, so no pass tests for it


def normalise(df: DataFrame, vec_col: str = "vec") -> DataFrame:
    size = norm(F.col(vec_col))
    return df.withColumn(vec_col, F.when(size > 0, F.transform(vec_col, lambda x: x / size)).otherwise(F.col(vec_col)))


def vectorise(df: DataFrame, id_col: str, cols: list[str], standardise: bool = True) -> DataFrame:
    """Numeric columns as vectors, optionally centred and scaled by the whole table."""
    if not standardise:
        return df.select(F.col(id_col).alias("point_id"), F.array(*[F.col(c).cast("double") for c in cols]).alias("vec"))
    stats = df.agg(*[f(c).alias(f"{n}_{c}") for c in cols for n, f in (("m", F.avg), ("s", F.stddev_pop))]).first()
    parts = [(F.col(c).cast("double") - stats[f"m_{c}"]) / (stats[f"s_{c}"] or 1.0) for c in cols]
    return df.select(F.col(id_col).alias("point_id"), F.array(*parts).alias("vec"))


GROUPS = {
    "intensity": ("letters", "digits", "uppers", "spaces"),
    "texture": ("distinct_chars", "repeat_bigrams"),
    "shape": ("mean_word", "max_word"),
    "layout": ("first_break", "n_breaks"),
    "density": ("emails", "phones", "links"),
    "matrix": ("markup", "punctuation"),
}


def handmade_features(tiles: DataFrame) -> DataFrame:
    """tile_id and structs of simple statistics, by group."""
    t, n = F.col("content"), F.length("content")
    share = lambda p: F.regexp_count(t, F.lit(p)) / n
    words = F.filter(F.split(t, "[ \\t\\r\\n]+"), lambda w: w != "")
    n_words = F.greatest(F.size(words), F.lit(1))
    chars = F.split(t, "")
    value = {
        "letters": share("[A-Za-zÀ-ÿ]"),
        "digits": share("[0-9]"),
        "uppers": share("[A-Z]"),
        "spaces": share("[ \\t\\r\\n]"),
        "distinct_chars": F.size(F.array_distinct(F.filter(chars, lambda c: c != ""))) / n,
        "repeat_bigrams": share("th|er|en|es|on"),
        "mean_word": F.aggregate(words, F.lit(0), lambda s, w: s + F.length(w)) / n_words,
        "max_word": F.coalesce(F.array_max(F.transform(words, lambda w: F.length(w))), F.lit(0)).cast("double"),
        "first_break": F.instr(t, "\n").cast("double"),
        "n_breaks": F.regexp_count(t, F.lit("\n")).cast("double"),
        "emails": F.regexp_count(t, F.lit("[a-z0-9.]+@[a-z0-9.]+")).cast("double"),
        "phones": F.regexp_count(t, F.lit("[0-9]{3}-[0-9]{4}")).cast("double"),
        "links": F.regexp_count(t, F.lit("https?://")).cast("double"),
        "markup": share("[<>{}|]"),
        "punctuation": share("[.,;:!?]"),
    }
    return tiles.where(n > 0).select(
        "tile_id", *[F.struct(*[value[c].alias(c) for c in cs]).alias(g) for g, cs in GROUPS.items()]
    )


def pca_project(points: DataFrame, m: int, width: int | None = None) -> DataFrame:
    """Projection on the m strongest directions; d x d sums leave the partitions and are added up before they
    reach the driver. width: length of the vectors, looked up if not given."""

    def sums(batches):
        total = None
        for pdf in batches:
            x = to_matrix(pdf["vec"])
            x = np.hstack([np.ones((len(x), 1)), x])
            total = x.T @ x if total is None else total + x.T @ x
        if total is not None:
            yield pd.DataFrame({"i": np.arange(len(total)), "row": list(total)})

    parts = points.select("vec").mapInPandas(sums, "i int, row array<double>")
    d = (points.agg(F.max(F.size("vec"))).first()[0] if width is None else width) or 0
    d = max(d, 0) + 1
    rows = parts.groupBy("i").agg(F.array(*[F.sum(F.get("row", F.lit(j))) for j in range(d)]).alias("row")).collect()
    gram = np.zeros((d, d))
    for r in rows:
        gram[r["i"]] += r["row"]
    n = max(gram[0, 0], 1)
    mean = gram[0, 1:] / n
    values, vectors = np.linalg.eigh(gram[1:, 1:] / n - np.outer(mean, mean))
    basis = vectors[:, np.argsort(-values)[:m]]
    basis = basis * np.where(basis[np.abs(basis).argmax(axis=0), np.arange(basis.shape[1])] < 0, -1.0, 1.0)
    return apply_matrix(points, basis, mean)


def random_project(points: DataFrame, d: int, m: int, seed: int = 1) -> DataFrame:
    return apply_matrix(points, np.random.default_rng(seed).normal(size=(d, m)) / np.sqrt(m), np.zeros(d))


def apply_matrix(points: DataFrame, matrix: np.ndarray, mean: np.ndarray | None = None) -> DataFrame:
    """Frozen linear features of every point."""
    shift = np.zeros(len(matrix)) if mean is None else mean

    @F.pandas_udf("array<double>")
    def project(vec: pd.Series) -> pd.Series:
        return pd.Series(list((to_matrix(vec) - shift) @ matrix) if len(vec) else [], dtype=object)

    return points.select("point_id", project("vec").alias("vec"))
