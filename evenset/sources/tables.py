"""Readers of the given tables and the slide/tile view of documents."""

from __future__ import annotations

import tempfile
import uuid

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F
from pyspark.sql import types as T

POINTS = T.StructType([T.StructField("point_id", T.LongType()), T.StructField("vec", T.ArrayType(T.DoubleType()))])


def table(spark: SparkSession, sf_dir: str, name: str, cast_ntz: bool = False) -> DataFrame:
    """A given table; cast_ntz turns zoneless timestamps into session-zone ones (watermarks need that)."""
    df = spark.read.parquet(f"{sf_dir}/{name}.parquet")
    if cast_ntz:
        zoneless = [f.name for f in df.schema.fields if isinstance(f.dataType, T.TimestampNTZType)]
        df = df.withColumns({c: F.col(c).cast("timestamp") for c in zoneless})
    return df


_LOCAL: dict[str, str] = {}


def shared_folder(spark: SparkSession) -> str:
    """The folder that the driver and all executors share. A temporary one, one a session, serves only where none is
    set and all runs on this machine (tests)."""
    context = spark.sparkContext
    base = context.getConf().get("spark.checkpoint.dir")
    if not base:
        if not context.master.startswith("local"):
            raise RuntimeError("set spark.checkpoint.dir to a folder that the driver and all executors share")
        base = _LOCAL.get(context.applicationId) or tempfile.mkdtemp(prefix="evenset-")
        _LOCAL[context.applicationId] = base
    return base.rstrip("/")


def staged(df: DataFrame) -> DataFrame:
    """The table written to the folder that all executors share and read again: used where a plan needs it
    more than once."""
    spark = df.sparkSession
    path = f"{shared_folder(spark)}/evenset-stage-{uuid.uuid4().hex}"
    df.write.parquet(path)
    return spark.read.schema(df.schema).parquet(path)


def spread(df: DataFrame) -> DataFrame:
    """More partitions where there are fewer than cores, so that iterations over a small input (one file, one
    row group) do not run in one task; large inputs pass unchanged."""
    cores = df.sparkSession.sparkContext.defaultParallelism
    return df.repartition(cores, "point_id") if df.rdd.getNumPartitions() < cores else df


def check_vectors(df: DataFrame, vec_col: str, mode: str = "fail") -> DataFrame:
    """Reject null vectors and null, NaN or infinite components: fail, drop, or count (adds vec_ok)."""
    good = F.coalesce(
        F.forall(vec_col, lambda x: x.isNotNull() & ~F.isnan(x) & (F.abs(x) < F.lit(float("inf")))), F.lit(False)
    )
    if mode == "drop":
        return df.where(good)
    if mode == "count":
        return df.withColumn("vec_ok", good)
    return df.withColumn(vec_col, F.when(good, F.col(vec_col)).otherwise(F.raise_error("bad vector")))


def slides(spark: SparkSession, sf_dir: str, width: int = 224) -> DataFrame:
    """Documents as slides: cohort by source number, tissue by language, diagnosis by source."""
    docs = table(spark, sf_dir, "documents")
    number = F.substring("source", 4, 10).cast("int")
    return docs.select(
        F.col("doc_id").alias("slide_id"),
        F.when(number < 10, "A").otherwise("B").alias("cohort"),
        F.col("lang").alias("tissue"),
        F.col("source").alias("diagnosis"),
        F.ceil(F.length("text") / width).cast("long").alias("n_tiles"),
    )


def make_tiles(docs: DataFrame, *, id_col: str = "doc_id", text_col: str = "text", width: int = 224) -> DataFrame:
    """Non-overlapping pieces of `width` characters; the last may be shorter. A text is cut in one go, whatever its
    length. Null and empty texts have no tile; a text of more than 2^20 tiles is refused, as ids would collide."""
    cut = F.regexp_extract_all(text_col, F.lit("(?s).{1,%d}" % width), F.lit(0))
    rows = docs.where(F.length(text_col) > 0).select(F.col(id_col).alias("slide_id"), F.posexplode(cut).alias("pos", "content"))
    number = F.when(F.col("pos") < 1 << 20, F.col("slide_id") * (1 << 20) + F.col("pos")).otherwise(F.raise_error("too many tiles"))
    return rows.select(number.alias("tile_id"), "slide_id", "pos", "content")


def fit_width(df: DataFrame, col: str, width: int = 224) -> DataFrame:
    """Pad or cut a text column to one width."""
    return df.withColumn(col, F.rpad(F.col(col), width, " "))


def detect_regions(tiles: DataFrame, min_letter_share: float = 0.5) -> DataFrame:
    """Foreground tiles: enough letters among the characters."""
    letters = F.regexp_count("content", F.lit("[A-Za-zÀ-ÿ]"))
    return tiles.where(letters >= min_letter_share * F.length("content"))


def visible_text(pages: DataFrame) -> DataFrame:
    """page_id and the text outside scripts, styles, navigation, comments and tags."""
    t = F.col("html")
    for pattern in VISIBLE:
        t = F.regexp_replace(t, pattern, " ")
    return pages.select("page_id", F.trim(F.regexp_replace(t, r"[ \t\r\n]+", " ")).alias("text"))


VISIBLE = (
    r"(?is)<script[^>]*>.*?</script>",
    r"(?is)<style[^>]*>.*?</style>",
    r"(?is)<nav[^>]*>.*?</nav>",
    r"(?is)<!--.*?-->",
    r"(?is)<[^>]*>",
)


def class_label(slides_df: DataFrame) -> DataFrame:
    """Supervised classes: tissue in cohort A, tissue and diagnosis in cohort B."""
    label = F.when(F.col("cohort") == "A", F.concat_ws(":", "cohort", "tissue")).otherwise(
        F.concat_ws(":", "cohort", "tissue", "diagnosis")
    )
    return slides_df.withColumn("class", label)
