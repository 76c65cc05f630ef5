"""Best-fit packing into bins of several permitted lengths.

Pieces go longest first into the open bin with the least room that still holds them. Where none does, the
bin length with the least cost per word that it can expect to carry is opened; at the end each bin shrinks
to the shortest permitted length that holds its contents.

Documents longer than the longest bin are cut into pieces, none is dropped. Shards of about `shard_docs`
documents, dealt by hash, are packed each by itself, so no task sees more than that.

Defined cases: documents without words take no room and get no piece; repeated rows are packed each: equal ids of
equal size are counted, and numbered before they are dealt, so they spread over the shards; a null id is kept as
null. Ids go through pandas as text, so all 64 bits of them hold beside a null.
"""

from __future__ import annotations

import numpy as np
import pandas as pd
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from .shared import read_table, word_count

CAPACITIES = (512, 1024, 2048, 4096)


def pack_shard(
    sizes: list[int], capacities: tuple[int, ...] = CAPACITIES, bin_cost: float = 16.0
) -> tuple[np.ndarray, np.ndarray, np.ndarray]:
    """(bin of each piece, its offset, final capacity of each bin). sizes: each at most max(capacities)."""
    caps = sorted(capacities)
    order = sorted(range(len(sizes)), key=lambda i: (-sizes[i], i))
    bins = np.zeros(len(sizes), np.int64)
    offset = np.zeros(len(sizes), np.int64)
    used: list[int] = []
    room: list[list[int]] = [[] for _ in range(caps[-1] + 1)]
    open_rooms = 0  # bit r is set if some bin has exactly r words of room
    left = sum(sizes)
    limit: list[int] = []
    for i in order:
        need = sizes[i]
        fits = open_rooms >> need
        if fits:
            r = need + (fits & -fits).bit_length() - 1
            b = room[r].pop()
            if not room[r]:
                open_rooms &= ~(1 << r)
        else:
            cap = min((c for c in caps if c >= need), key=lambda c: ((c + bin_cost) / min(c, left), c))
            b, r = len(used), cap
            used.append(0)
            limit.append(cap)
        bins[i], offset[i] = b, used[b]
        used[b] += need
        left -= need
        r -= need
        if r:
            room[r].append(b)
            open_rooms |= 1 << r
    final = np.array([next(c for c in caps if c >= u) for u in used], np.int64)
    return bins, offset, final


def pack_documents(
    docs: DataFrame,
    *,
    id_col: str = "doc_id",
    text_col: str = "text",
    size_col: str | None = None,
    capacities: tuple[int, ...] = CAPACITIES,
    bin_cost: float = 16.0,
    shard_docs: int = 4000,
) -> DataFrame:
    """A row per piece: doc_id, piece, start (word of the text), n_words, shard, bin, bin_offset,
    bin_capacity, bin_used."""
    top = max(capacities)
    size = word_count(F.col(text_col)) if size_col is None else F.col(size_col).cast("long")
    rows = docs.select(F.col(id_col).cast("long").cast("string").alias("doc_id"), size.alias("size")).where("size > 0")
    shards = max(1, -(-docs.select(id_col).count() // shard_docs))
    pieces = (
        rows.groupBy("doc_id", "size")
        .agg(F.count("*").cast("int").alias("rows"))
        .withColumn("copy", F.explode(F.sequence(F.lit(1), F.col("rows"))))
        .withColumn("piece", F.explode(F.sequence(F.lit(0), F.expr(f"cast((size - 1) div {top} as int)"))))
        .withColumn("start", F.col("piece").cast("long") * top)
        .withColumn("n_words", F.least(F.lit(top).cast("long"), F.col("size") - F.col("start")))
        .withColumn("shard", F.pmod(F.xxhash64("doc_id", "piece", "size", "copy"), F.lit(shards)))
    )

    def pack(pdf: pd.DataFrame) -> pd.DataFrame:
        turn = ["n_words", "doc_id", "piece", "copy"]
        pdf = pdf.sort_values(turn, ascending=[False, True, True, True], ignore_index=True)
        bins, offset, final = pack_shard([int(x) for x in pdf["n_words"]], capacities, bin_cost)
        used = np.bincount(bins, pdf["n_words"], len(final)).astype(np.int64)
        return pdf.drop(columns="copy").assign(bin=bins, bin_offset=offset, bin_capacity=final[bins], bin_used=used[bins])

    schema = (
        "doc_id string, piece int, start long, n_words long, shard long, bin long, bin_offset long, "
        "bin_capacity long, bin_used long"
    )
    cols = ("doc_id", "piece", "start", "n_words", "shard", "copy")
    packed = pieces.select(*cols).groupBy("shard").applyInPandas(pack, schema)
    return packed.withColumn("doc_id", F.col("doc_id").cast("long"))


def op10_best_fit_packing(spark: SparkSession, sf_dir: str) -> DataFrame:
    return pack_documents(read_table(spark, sf_dir, "documents"))
