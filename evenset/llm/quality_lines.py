"""Quality rules from cross-document line frequency.

Every line is normalised (ASCII lower case, digits to 0, white space squeezed) and hashed; per host the
distinct documents that hold it are counted. Lines above the limit are boilerplate and go; a document that
loses too many of its words is rejected as depleted.

Exact copies count once: a document's family is the digest of the whole set of its normalised lines, so only
documents with the same set of lines add one to a line's count together. Without this, every line of a page
copied a thousand times would look like boilerplate and the page itself would vanish. Near copies differ in
their sets, so each of them counts.

Defined cases: a null or empty text has no words and fails the base rules; null hosts are one host; repeated
rows get equal results; lines without a word are never counted.
"""

from __future__ import annotations

from collections.abc import Iterator

import numpy as np
import pandas as pd
import xxhash
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from .shared import join_weighted, keep_table, read_table, spare_name

# Symbols counted by the base rules.
SYMBOLS = "#*$%&|<>"
WINDOW = 8

_PROFILE = (
    "row_key string, doc_id long, host string, n_words long, word_chars long, n_symbols long, "
    "n_dup_lines long, n_repeat_words long, family long, line_hash array<long>, line_words array<int>"
)


def repeated_words(codes: np.ndarray, window: int = WINDOW) -> int:
    """Words inside windows that occur at least twice; codes: one number per distinct word."""
    n = len(codes)
    if n <= window:
        return 0
    # rank windows by doubling, so equal ranks mean equal windows without any hash collision
    rank, width = codes, 1
    while width < window:
        pairs = rank[:-width].astype(np.int64) * (int(rank.max()) + 1) + rank[width:]
        rank = np.unique(pairs, return_inverse=True)[1]
        width *= 2
    starts = np.bincount(rank)[rank] > 1
    edge = np.zeros(n + 1, np.int64)
    at = np.flatnonzero(starts)
    np.add.at(edge, at, 1)
    np.add.at(edge, at + window, -1)
    return int((np.cumsum(edge)[:n] > 0).sum())


_DIGITS = bytes.maketrans(b"ABCDEFGHIJKLMNOPQRSTUVWXYZ123456789", b"abcdefghijklmnopqrstuvwxyz000000000")


def line_set_digest(hashes: list[int]) -> int | None:
    """One number for the set of lines, whatever their order and repeats; None without a line."""
    return xxhash.xxh64_intdigest(np.unique(np.array(hashes, np.int64)).tobytes()) - (1 << 63) if hashes else None


def profile_text(text: str) -> tuple:
    """(n_words, word_chars, n_symbols, n_dup_lines, n_repeat_words, family, line hashes, words per line)."""
    raw = text.encode("utf-8", "surrogatepass")
    words = raw.split()
    table: dict[bytes, int] = {}
    codes = np.fromiter((table.setdefault(w, len(table)) for w in words), np.int64, len(words))
    joined = b"".join(words)
    word_chars = len(joined.decode("utf-8", "surrogatepass"))
    seen: set[bytes] = set()
    dup, hashes, sizes = 0, [], []
    for line in raw.split(b"\n"):
        held = line.translate(_DIGITS).split()
        if not held:
            continue
        dup += line in seen
        seen.add(line)
        hashes.append(xxhash.xxh64_intdigest(b" ".join(held)) - (1 << 63))
        sizes.append(len(held))
    return (
        len(words),
        word_chars,
        sum(text.count(c) for c in SYMBOLS),
        dup,
        repeated_words(codes),
        line_set_digest(hashes),
        hashes,
        sizes,
    )


def _profiles(batches: Iterator[pd.DataFrame]) -> Iterator[pd.DataFrame]:
    for pdf in batches:
        rows = [profile_text(t or "") for t in pdf["text"]]
        cols = list(zip(*rows)) if rows else [()] * 8
        yield pd.DataFrame(
            {
                "row_key": pdf["row_key"],
                "doc_id": pdf["doc_id"].astype("Int64"),
                "host": pdf["host"],
                "n_words": cols[0],
                "word_chars": cols[1],
                "n_symbols": cols[2],
                "n_dup_lines": cols[3],
                "n_repeat_words": cols[4],
                "family": pd.array(cols[5], dtype="Int64"),
                "line_hash": list(cols[6]),
                "line_words": list(cols[7]),
            }
        )


def line_quality(
    docs: DataFrame,
    *,
    id_col: str = "doc_id",
    text_col: str = "text",
    host_col: str = "source",
    max_docs: int = 20,
    max_lost: float = 0.6,
) -> DataFrame:
    """Verdict per row: base counts, words lost to boilerplate lines, and kept.

    max_docs: a line in more distinct documents of a host (exact copies counting once) is boilerplate.
    max_lost: a document that loses more than this share of its words is depleted.
    """
    host = F.when(F.col(host_col).isNull(), "0").otherwise(F.concat(F.lit("1"), F.col(host_col)))
    text = F.coalesce(F.col(text_col), F.lit(""))
    src = docs.select(
        F.concat_ws(":", F.coalesce(F.col(id_col).cast("string"), F.lit("-")), F.md5(text), host).alias("row_key"),
        F.col(id_col).cast("long").alias("doc_id"),
        host.alias("host"),
        text.alias("text"),
    )
    profile = keep_table(src.mapInPandas(_profiles, _PROFILE), "lines")
    lines = profile.select(
        "row_key", "host", "family", F.explode(F.arrays_zip("line_hash", "line_words")).alias("x")
    ).select("row_key", "host", "family", "x.line_hash", "x.line_words")
    common = (
        lines.groupBy("host", "line_hash", "family")
        .agg(F.count("*").alias("n"))
        .groupBy("host", "line_hash")
        .agg(F.count("*").alias("holders"), F.sum("n").alias("n"))
        .where(F.col("holders") > max_docs)
    )
    common = keep_table(common.drop("holders"), "common-lines")
    total = profile.agg(F.sum(F.size("line_hash"))).first()[0] or 0
    # repeated rows share a row_key: their lines are counted once for each, so take the mean
    lost = join_weighted(lines, common, ["host", "line_hash"], "n", total).groupBy("row_key").agg(F.sum("line_words").alias("lost"))
    copies = profile.groupBy("row_key").agg(F.count("*").alias("copies"))
    lost = lost.join(copies, "row_key").select("row_key", (F.col("lost") / F.col("copies")).cast("long").alias("lost"))
    base_failed = (F.col("n_words") < 20) | (100 * F.col("n_repeat_words") > 30 * F.col("n_words"))
    out = profile.drop("line_hash", "line_words", "family", "host").join(lost, "row_key", "left")
    n_lost = F.coalesce(F.col("lost"), F.lit(0)).cast("long")
    return out.select(
        "row_key",
        "doc_id",
        "n_words",
        "word_chars",
        "n_symbols",
        "n_dup_lines",
        "n_repeat_words",
        base_failed.alias("base_failed"),
        n_lost.alias("n_lost_words"),
        (~base_failed & (n_lost <= max_lost * F.col("n_words"))).alias("kept"),
    )


def keep_good(docs: DataFrame, **options) -> DataFrame:
    """The rows of docs that line_quality keeps, columns unchanged."""
    id_col, text_col, host_col = (
        options.get(k, v) for k, v in (("id_col", "doc_id"), ("text_col", "text"), ("host_col", "source"))
    )
    name = spare_name(docs, "row_key")
    good = line_quality(docs, **options).where("kept").select(F.col("row_key").alias(name)).distinct()
    host = F.when(F.col(host_col).isNull(), "0").otherwise(F.concat(F.lit("1"), F.col(host_col)))
    key = F.concat_ws(
        ":",
        F.coalesce(F.col(id_col).cast("string"), F.lit("-")),
        F.md5(F.coalesce(F.col(text_col), F.lit(""))),
        host,
    )
    return docs.withColumn(name, key).join(good, name, "left_semi").select(*docs.columns)


def op7_line_quality(spark: SparkSession, sf_dir: str) -> DataFrame:
    return line_quality(read_table(spark, sf_dir, "documents")).drop("row_key")


# Windows, lines and sets of lines as they are, without hashes; Java's and Python's ASCII white space alike.
OP7_SQL = r"""
WITH d AS (SELECT row_number() OVER () AS i, doc_id, source AS host, coalesce(text, '') AS t FROM documents),
w AS (SELECT i, regexp_extract_all(t, '[^\x20\x09-\x0D]+') AS w, t FROM d),
b AS (SELECT i, len(w) AS n_words, length(array_to_string(w, '')) AS word_chars, length(regexp_replace(t, '[^#*$%&|<>]', '', 'g')) AS n_symbols FROM w),
g AS (SELECT i, p, array_to_string(w[p:p + 7], ' ') AS x FROM w, unnest(range(1, len(w) - 6)) AS u(p)),
k AS (SELECT i, p, count(*) OVER (PARTITION BY i, x) AS n FROM g),
q AS (SELECT i, count(DISTINCT p + o) AS n_repeat_words FROM k, unnest(range(0, 8)) AS u(o) WHERE n > 1 GROUP BY i),
l AS (SELECT i, x, [translate(y, 'ABCDEFGHIJKLMNOPQRSTUVWXYZ123456789', 'abcdefghijklmnopqrstuvwxyz000000000') FOR y IN regexp_extract_all(x, '[^\x20\x09-\x0D]+')] AS ws
  FROM d, unnest(string_split(t, chr(10))) AS u(x)),
m AS (SELECT i, x, len(ws) AS n, array_to_string(ws, ' ') AS line FROM l WHERE len(ws) > 0),
u AS (SELECT i, count(*) - count(DISTINCT x) AS n_dup_lines, array_to_string(list_sort(list(DISTINCT line)), chr(10)) AS family FROM m GROUP BY i),
c AS (SELECT host, line FROM m JOIN d USING (i) JOIN u USING (i) GROUP BY host, line HAVING count(DISTINCT family) > 20),
z AS (SELECT m.i, sum(m.n) AS lost FROM m JOIN d ON m.i = d.i JOIN c ON c.line = m.line AND c.host IS NOT DISTINCT FROM d.host GROUP BY m.i),
r AS (SELECT doc_id, n_words, word_chars, n_symbols, coalesce(n_dup_lines, 0) AS n_dup_lines, coalesce(n_repeat_words, 0) AS n_repeat_words, coalesce(lost, 0) AS lost
  FROM d JOIN b USING (i) LEFT JOIN q USING (i) LEFT JOIN u USING (i) LEFT JOIN z USING (i))
SELECT doc_id, CAST(n_words AS BIGINT) AS n_words, CAST(word_chars AS BIGINT) AS word_chars, CAST(n_symbols AS BIGINT) AS n_symbols,
  CAST(n_dup_lines AS BIGINT) AS n_dup_lines, CAST(n_repeat_words AS BIGINT) AS n_repeat_words,
  n_words < 20 OR 100 * n_repeat_words > 30 * n_words AS base_failed, CAST(lost AS BIGINT) AS n_lost_words,
  NOT (n_words < 20 OR 100 * n_repeat_words > 30 * n_words) AND lost <= 0.6::DOUBLE * n_words AS kept FROM r
"""
