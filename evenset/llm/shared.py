"""Helpers that the operators of this subpackage have in common."""

from __future__ import annotations

import tempfile
import uuid

from pyspark.sql import Column, DataFrame, SparkSession, Window
from pyspark.sql import functions as F

# Fixed value: what the contracts call a word.
WORD = r"[^\x20\x09-\x0D]+"


_LOCAL: dict[str, str] = {}


def shared_dir(spark: SparkSession) -> str:
    """The folder that driver and executors share. A temporary one, one a session, serves only where none is set and
    all runs on this machine (tests)."""
    context = spark.sparkContext
    found = context.getConf().get("spark.checkpoint.dir")
    if not found:
        if not context.master.startswith("local"):
            raise RuntimeError("set spark.checkpoint.dir to a folder that the driver and all executors share")
        found = _LOCAL.setdefault(context.applicationId, "") or tempfile.mkdtemp(prefix="evenset-")
        _LOCAL[context.applicationId] = found
    return found.rstrip("/")


def fresh_path(spark: SparkSession, name: str) -> str:
    return f"{shared_dir(spark)}/evenset-{name}-{uuid.uuid4().hex}"


def keep_table(df: DataFrame, name: str) -> DataFrame:
    """Write a table into the shared folder and read it back: cuts lineage, survives lost executors."""
    spark = df.sparkSession
    path = fresh_path(spark, name)
    df.write.parquet(path)
    return spark.read.schema(df.schema).parquet(path)


def spare_name(df: DataFrame, base: str) -> str:
    """A column name that the table does not have."""
    while base in df.columns:
        base += "_"
    return base


def word_count(text: Column) -> Column:
    """Words of the whole text; null counts as empty."""
    return F.regexp_count(F.coalesce(text, F.lit("")), F.lit(WORD)).cast("long")


def id_remainder(doc_id: Column, modulus: int) -> Column:
    """crc32 of the id's decimal text, modulo; a null id counts as the empty text (remainder 0)."""
    return F.pmod(F.crc32(F.coalesce(doc_id.cast("string"), F.lit("")).cast("binary")), F.lit(modulus))


def read_table(spark: SparkSession, sf_dir: str, name: str) -> DataFrame:
    return spark.read.parquet(f"{sf_dir}/{name}.parquet")


def join_weighted(
    left: DataFrame, right: DataFrame, keys: list[str], weight: str, total: int, parts: int = 512, floor: int = 1000
) -> DataFrame:
    """Inner join of rows with a table of one row per key, whose column `weight` says how many rows of left hold
    the key; total: all rows of left, or more. Keys with over total / parts rows (and over `floor`) are fewer than
    `parts`; they are broadcast, so no task gets a heavy key, and all others meet in a shuffle."""
    heavy = F.col(weight) > max(total // parts, floor)
    hot = right.where(heavy)
    if not hot.take(1):
        return left.join(right, keys)
    met = left.join(F.broadcast(hot), keys)
    rest = left.join(F.broadcast(hot.select(*keys)), keys, "left_anti").join(right.where(~heavy), keys)
    return met.unionByName(rest)


def sums_before(df: DataFrame, order: list[Column], values: dict[str, Column], parts: int | None = None) -> DataFrame:
    """+ per name the sum of a value over all rows that come earlier in a global order (0 for the first row).

    Rows go to range partitions, which are written once, since range bounds come from a sample and two runs need not
    agree; only one row per partition meets in a single window."""
    spark = df.sparkSession
    parts = parts or int(spark.conf.get("spark.sql.shuffle.partitions"))
    keys = {f"__order{i}": c for i, c in enumerate(order)}
    keyed = df.withColumns({**keys, **{f"__{n}": c for n, c in values.items()}})
    keyed = keyed.repartitionByRange(parts, *keys).sortWithinPartitions(*keys)
    keyed = keep_table(keyed.withColumn("__part", F.spark_partition_id()).withColumn("__at", F.monotonically_increasing_id()), "ranges")
    earlier = Window.orderBy("__part").rowsBetween(Window.unboundedPreceding, -1)
    per = keyed.groupBy("__part").agg(*[F.sum(f"__{n}").alias(n) for n in values])
    per = per.select("__part", *[F.coalesce(F.sum(n).over(earlier), F.lit(0)).alias(f"__base_{n}") for n in values])
    inside = Window.partitionBy("__part").orderBy("__at").rowsBetween(Window.unboundedPreceding, -1)
    out = keyed.withColumns({n: F.coalesce(F.sum(f"__{n}").over(inside), F.lit(0)) for n in values})
    out = out.join(F.broadcast(per), "__part")  # one row per range
    return out.select(*df.columns, *[(F.col(n) + F.col(f"__base_{n}")).alias(n) for n in values])


def text_blocks(docs: DataFrame, text_col: str, block_bytes: int) -> int:
    """How many hash blocks of about block_bytes of text the table makes; one cheap scan."""
    total = docs.agg(F.sum(F.octet_length(text_col))).first()[0] or 0
    return max(1, -(-int(total) // block_bytes))
