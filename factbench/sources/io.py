"""Reading tables and feeds with declared schemas; writing splits so that reruns replace, not repeat."""

from __future__ import annotations

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F
from pyspark.sql import types as T

#: Rows up to which a side of a join is sent to all executors.
SMALL = 1_000_000

TABLES = ("region", "nation", "customer", "supplier", "part", "orders", "lineitem", "events", "documents", "embeddings", "pages", "benchmark", "labels", "conversations")

#: A record of the review feed: one claim, one or more reviews of it.
REVIEW = T.StructType(
    [
        T.StructField("claimReviewed", T.StringType()),
        T.StructField("inLanguage", T.StringType()),
        T.StructField("datePublished", T.DateType()),
        T.StructField("url", T.StringType()),
        T.StructField("author", T.StructType([T.StructField("name", T.StringType())])),
        T.StructField("reviewRating", T.StructType([T.StructField("alternateName", T.StringType())])),
        T.StructField("itemReviewed", T.StructType([T.StructField("appearance", T.ArrayType(T.StructType([T.StructField("url", T.StringType())])))])),
    ]
)


def small(df: DataFrame, most: int = SMALL) -> DataFrame:
    """``df`` marked for broadcasting if it has at most ``most`` rows, else as it is; counts no further than that."""
    return F.broadcast(df) if df.limit(most + 1).count() <= most else df  # the same object if it is too long


def work_dir(spark: SparkSession) -> str:
    """A folder that all executors see: the one in spark.checkpoint.dir, else one in the warehouse; a temporary one in local mode alone."""
    named = spark.conf.get("spark.checkpoint.dir", None)
    if not named:
        if spark.sparkContext.master.startswith("local"):
            import tempfile

            named = tempfile.mkdtemp(prefix="factbench-")
        else:
            named = f"{spark.conf.get('spark.sql.warehouse.dir').rstrip('/')}/_factbench"
    return named.rstrip("/")


def checkpointed(df: DataFrame) -> DataFrame:
    """``df`` computed once and cut from its lineage, in the shared folder."""
    spark = df.sparkSession
    if spark.sparkContext._jsc.sc().getCheckpointDir().isEmpty():
        spark.sparkContext.setCheckpointDir(work_dir(spark))
    return df.checkpoint()


def spread(df: DataFrame) -> DataFrame:
    """A scan of fewer splits than half the cores, dealt over all of them; larger scans are left as they are."""
    cores = df.sparkSession.sparkContext.defaultParallelism
    return df.repartition(cores) if 2 * df.rdd.getNumPartitions() < cores else df


def load(spark: SparkSession, folder: str, name: str, columns: list[str] | None = None) -> DataFrame:
    """A given table; only ``columns`` reach the scan if named."""
    if name not in TABLES:
        raise ValueError(f"no table {name}")
    df = spark.read.parquet(f"{folder}/{name}.parquet")
    return df.select(*columns) if columns else df


def read_lines(spark: SparkSession, path: str) -> DataFrame:
    """A feed of one JSON text a line, not parsed yet."""
    return spark.read.text(path).withColumnRenamed("value", "raw")


def read_json(spark: SparkSession, path: str, schema: T.StructType) -> DataFrame:
    return spark.read.schema(schema).json(path)


def read_csv(spark: SparkSession, path: str, schema: T.StructType) -> DataFrame:
    return spark.read.schema(schema).csv(path, header=True)


def write_split(df: DataFrame, path: str, by: str = "quarter", rows_per_file: int = 2_000_000) -> None:
    """Write partitioned Parquet; a rerun replaces the partitions it has rows for and leaves the others."""
    (
        df.repartition(by, F.pmod(F.xxhash64(*df.columns[:1]), F.lit(16)))
        .write.mode("overwrite")
        .option("partitionOverwriteMode", "dynamic")
        .option("maxRecordsPerFile", rows_per_file)
        .partitionBy(by)
        .parquet(path)
    )


def write_json(df: DataFrame, path: str) -> None:
    df.write.mode("overwrite").json(path)


def write_csv(df: DataFrame, path: str) -> None:
    df.write.mode("overwrite").csv(path, header=True)
