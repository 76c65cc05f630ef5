"""Exact top-k by inner product over a bit-sliced index.

Rows are dealt into blocks. A block stores, per attribute, the high bits of the values as bitmaps over its
rows (slices). A query adds the slices, weighted by the bits of its own quantised attributes, with bitmap
arithmetic (carry-save adders over whole words of rows); the sum is again a set of slices. Walking them from
the most significant one down finds the k-th greatest approximate sum without unpacking any row. Rows within
the proven quantisation error of it are the boundary rows, and only those get the exact integer product.

Queries are blocks too: every block of queries meets every block of rows by an equi-join on the block number,
so neither side is ever collected or broadcast.

Defined cases: null vectors, and vectors with null or non-finite components or of a length that is not the
most frequent one (of equally frequent ones the shortest), take no part; of rows that share an id only the one
of the least vector does; a null id takes no part; ties go to the smaller id; a row is never its own query's result.
"""

from __future__ import annotations

from collections.abc import Iterator

import numpy as np
import pandas as pd
from pyspark.sql import DataFrame, SparkSession, Window
from pyspark.sql import functions as F

from .shared import keep_table, read_table

HALF = np.uint64(0xFFFFFFFFFFFFFFFF)


class SliceIndex:
    """Bit slices of an integer matrix (rows x attributes), quantised per attribute to `bits` bits."""

    def __init__(self, values: np.ndarray, bits: int = 4):
        self.values = np.ascontiguousarray(values, np.int64)
        self.n, self.dim = values.shape
        self.low = self.values.min(axis=0)
        span = self.values.max(axis=0) - self.low
        self.shift = np.array([max(0, int(s).bit_length() - bits) for s in span])
        codes = (self.values - self.low) >> self.shift
        self.words = -(-self.n // 64)
        padded = np.zeros((self.words * 64, self.dim), np.uint8)
        padded[: self.n] = codes
        self.bits = bits
        # slices[j, b]: bitmap of bit b of attribute j over the rows
        self.slices = np.stack(
            [np.packbits(padded >> b & 1, axis=0, bitorder="little").T.copy().view(np.uint64) for b in range(bits)],
            axis=1,
        )


def _push(columns: list[list[np.ndarray]], w: int, bitmap: np.ndarray) -> None:
    """Put a bitmap of weight 2**w; three of a weight become one of it and one of the next (full adder), so
    at most two of each weight live at a time."""
    column = columns[w]
    column.append(bitmap)
    if len(column) == 3:
        a, b, c = column
        ab = a ^ b
        columns[w] = [ab ^ c]
        _push(columns, w + 1, (a & b) | (c & ab))


def _add_slices(columns: list[list[np.ndarray]]) -> list[np.ndarray]:
    """Sum of bitmaps by weight (columns[w] has weight 2**w) as one bitmap per bit of the sum."""
    out, w = [], 0
    while w < len(columns):
        column = columns[w]
        if w + 1 == len(columns) and len(column) > 1:
            columns.append([])
        while len(column) > 2:
            a, b, c = column.pop(), column.pop(), column.pop()
            ab = a ^ b
            columns[w + 1].append((a & b) | (c & ab))
            column.insert(0, ab ^ c)
        if len(column) == 2:
            a, b = column
            columns[w + 1].append(a & b)
            column[:] = [a ^ b]
        out.append(column[0] if column else None)
        w += 1
    return out


def _count(bitmaps: np.ndarray) -> np.ndarray:
    return np.bitwise_count(bitmaps).sum(axis=-1)


def search_block(
    index: SliceIndex, row_ids: np.ndarray, queries: np.ndarray, query_ids: np.ndarray, k: int, query_bits: int = 4
) -> Iterator[tuple[int, int, int]]:
    """(query_id, row_id, score) of at most k + 1 rows per query: the best of this block, ties to smaller ids."""
    q = np.ascontiguousarray(queries, np.int64)
    n_q, dim = q.shape
    size = np.abs(q)
    drop = np.maximum(0, np.array([int(x).bit_length() for x in size.max(axis=1)]) - query_bits)
    coarse = size >> drop[:, None]
    shape = (n_q, index.words)
    full = np.where(q >= 0, np.uint64(0), HALF)
    # attributes of unequal shift land in columns of unequal weight
    columns: list[list[np.ndarray]] = [[] for _ in range(query_bits + index.bits + int(index.shift.max()) + 8)]
    for a in range(query_bits):
        on = np.where(coarse >> a & 1, HALF, np.uint64(0))
        for j in range(dim):
            if not on[:, j].any():
                continue
            for b in range(index.bits):
                # a negative weight adds the complement of the slice; the constant is put back below
                bitmap = np.bitwise_and(index.slices[j, b][None, :] ^ full[:, j, None], on[:, j, None])
                _push(columns, a + b + int(index.shift[j]), bitmap)
    sums = _add_slices(columns)
    valid = np.zeros(index.words * 64, np.uint8)
    valid[: index.n] = 1
    valid = np.packbits(valid, bitorder="little").view(np.uint64)
    keep = min(k + 1, index.n)  # one more, since the query itself may be among them
    # k-th greatest approximate sum: from the most significant slice down, keep the side that holds it
    tied = np.broadcast_to(valid, shape).copy()
    need = np.full(n_q, keep)
    floor = np.zeros(n_q, np.int64)
    live = [(w, s) for w, s in enumerate(sums) if s is not None]
    for w, s in reversed(live):
        ones = tied & s
        found = _count(ones)
        hit = found >= need
        need = np.where(hit, need, need - found)
        floor += np.where(hit, np.int64(1) << w, 0)
        tied = np.where(hit[:, None], ones, tied & ~s)
    # exact = 2**drop * sum + terms that the dropped bits can move by at most `slack` in all
    top = (1 << index.bits) - 1
    span = (np.int64(top) << index.shift) + (np.int64(1) << index.shift) - 1
    lost_row = (size * ((np.int64(1) << index.shift) - 1)[None, :]).sum(axis=1)
    lost_query = ((size - (coarse << drop[:, None])) * span[None, :]).sum(axis=1)
    reach = -(-(lost_row + lost_query) // (np.int64(1) << drop))
    bound = np.maximum(0, floor - reach - 1)
    # rows whose approximate sum is at least bound, again by slices
    above = np.zeros(shape, np.uint64)
    equal = np.broadcast_to(valid, shape).copy()
    for w, s in reversed(live):
        bit = (bound >> w & 1).astype(bool)[:, None]
        above = np.where(bit, above, above | (equal & s))
        equal = np.where(bit, equal & s, equal & ~s)
    # a bound above what the slices can hold never happens: it is at most the k-th sum itself
    boundary = above | equal
    rows = np.unpackbits(boundary.view(np.uint8), axis=1, bitorder="little")
    for i in range(n_q):
        at = np.flatnonzero(rows[i])
        at = at[row_ids[at] != query_ids[i]]
        if len(at) == 0:
            continue
        score = index.values[at] @ q[i]
        for x in np.lexsort((row_ids[at], -score))[:k]:
            yield int(query_ids[i]), int(row_ids[at[x]]), int(score[x])


def quantise(vectors: DataFrame, *, id_col: str = "vec_id", vec_col: str = "embedding", scale: int = 256) -> DataFrame:
    """id and the integer vector floor(scale * x); rows that take no part are gone."""
    wide = F.transform(F.col(vec_col), lambda x: x.cast("double"))
    sound = F.forall(wide, lambda x: x.isNotNull() & ~F.isnan(x) & (F.abs(x) < F.lit(float("inf"))))
    rows = vectors.where(F.col(vec_col).isNotNull() & F.col(id_col).isNotNull())
    rows = rows.where(F.coalesce(sound, F.lit(False)) & (F.size(vec_col) > 0))
    codes = F.transform(wide, lambda x: F.floor(x * scale).cast("long"))
    return rows.select(F.col(id_col).cast("long").alias("vec_id"), codes.alias("codes"))


def top_k(
    rows: DataFrame,
    queries: DataFrame,
    *,
    k: int = 5,
    block_rows: int = 4096,
    block_queries: int = 256,
) -> DataFrame:
    """rows, queries: (vec_id, codes). Returns query_id, rank, vec_id, score."""

    def blocks(df: DataFrame, size: int, name: str) -> tuple[DataFrame, int]:
        n = df.agg(F.count("*")).first()[0]
        parts = max(1, -(-n // size))
        numbered = df.withColumn(name, F.pmod(F.xxhash64("vec_id"), F.lit(parts)).cast("int"))
        packed = numbered.groupBy(name).agg(F.collect_list(F.struct("vec_id", "codes")).alias(f"{name}_rows"))
        return packed, parts

    row_blocks, n_rows = blocks(rows, block_rows, "rb")
    query_blocks, _ = blocks(queries, block_queries, "qb")
    meets = query_blocks.withColumn("rb", F.explode(F.sequence(F.lit(0), F.lit(n_rows - 1))))

    def run(batches: Iterator[pd.DataFrame]) -> Iterator[pd.DataFrame]:
        last, index, ids = None, None, None
        for pdf in batches:
            for rb, held, asked in zip(pdf["rb"], pdf["rb_rows"], pdf["qb_rows"]):
                if rb != last:
                    ids = np.array([x["vec_id"] for x in held], np.int64)
                    index, last = SliceIndex(np.array([x["codes"] for x in held], np.int64)), rb
                q_ids = np.array([x["vec_id"] for x in asked], np.int64)
                q = np.array([x["codes"] for x in asked], np.int64)
                found = list(search_block(index, ids, q, q_ids, k))
                yield pd.DataFrame(found, columns=["query_id", "vec_id", "score"], dtype="int64")

    pairs = row_blocks.join(meets.hint("shuffle_hash"), "rb").select("rb", "rb_rows", "qb_rows")
    best = pairs.mapInPandas(run, "query_id long, vec_id long, score long")
    turn = Window.partitionBy("query_id").orderBy(F.desc("score"), "vec_id")
    ranked = best.withColumn("rank", F.row_number().over(turn)).where(F.col("rank") <= k)
    return ranked.select("query_id", F.col("rank").cast("int").alias("rank"), "vec_id", "score")


def one_length(rows: DataFrame) -> DataFrame:
    """Quantised rows of the most frequent length, one for each id; written once, for both sides of the search."""
    sizes = rows.groupBy(F.size("codes").alias("n")).count().orderBy(F.desc("count"), "n").limit(1).collect()
    rows = rows.where(F.size("codes") == (sizes[0]["n"] if sizes else 0))
    return keep_table(rows.groupBy("vec_id").agg(F.min("codes").alias("codes")), "codes")


def op3_bit_sliced_topk(spark: SparkSession, sf_dir: str) -> DataFrame:
    rows = one_length(quantise(read_table(spark, sf_dir, "embeddings")))
    return top_k(rows, rows.where("vec_id % 50 = 0"))


OP3_SQL = """
WITH w AS (
  SELECT vec_id, [CAST(floor(256 * CAST(x AS DOUBLE)) AS BIGINT) FOR x IN embedding] AS c FROM embeddings
  WHERE vec_id IS NOT NULL AND embedding IS NOT NULL AND len([x FOR x IN embedding IF x IS NULL OR NOT isfinite(x)]) = 0),
v AS (
  SELECT vec_id, min(c) AS c FROM w
  WHERE len(c) = (SELECT n FROM (SELECT len(c) AS n, count(*) AS k FROM w WHERE len(c) > 0 GROUP BY 1) x ORDER BY k DESC, n LIMIT 1) GROUP BY 1),
s AS (
  SELECT q.vec_id AS query_id, r.vec_id AS vec_id, CAST(list_inner_product([CAST(x AS DOUBLE) FOR x IN q.c], [CAST(x AS DOUBLE) FOR x IN r.c]) AS BIGINT) AS score
  FROM v q JOIN v r ON q.vec_id <> r.vec_id WHERE q.vec_id % 50 = 0),
t AS (SELECT *, CAST(row_number() OVER (PARTITION BY query_id ORDER BY score DESC, vec_id) AS INTEGER) AS rank FROM s)
SELECT query_id, rank, vec_id, score FROM t WHERE rank <= 5
"""
