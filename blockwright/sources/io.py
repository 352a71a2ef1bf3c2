"""Tables in, blocks and plans out."""

from __future__ import annotations

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F
from pyspark.sql.types import StructType

from ..model import BlockingSpec, BlockTree, RoundPlan


def load_tables(spark: SparkSession, folder: str, names: list[str]) -> dict[str, DataFrame]:
    return {n: spark.read.parquet(f"{folder}/{n}.parquet") for n in names}


def read_feed(spark: SparkSession, path: str, schema: StructType | str, form: str = "csv", **options) -> DataFrame:
    """A new feed with a given schema: csv, json, text, parquet or orc; or "table" (catalog) and "jdbc" with their options."""
    if form == "table":
        return spark.read.table(path)
    reader = spark.read.options(**options)
    return (reader.format(form) if form == "jdbc" else reader.schema(schema).format(form)).load(path) if form != "jdbc" else reader.format("jdbc").load()


def validate(df: DataFrame, spec: BlockingSpec) -> None:
    """Raise unless ids are unique and not null and every attribute's expression resolves."""
    df.select(*[F.expr(a.expr).alias(a.name) for a in spec.attributes])
    bad = df.groupBy(spec.id_col).agg(F.count("*").alias("n")).where((F.col("n") > 1) | F.col(spec.id_col).isNull())
    if not bad.isEmpty():
        raise ValueError(f"{spec.id_col} is null or not unique")


def save_blocks(assigned: DataFrame, path: str, buckets: int = 64, bucketed: bool = False) -> None:
    """Write an assignment by hashed block; `bucketed` saves a table (path is its name) whose later joins on the block need no shuffle."""
    if bucketed:
        assigned.write.bucketBy(buckets, "block_key").sortBy("block_key").mode("overwrite").saveAsTable(path)
    else:
        assigned.withColumn("bucket", F.pmod(F.xxhash64("block_key"), F.lit(buckets)).cast("int")).repartition("bucket").sortWithinPartitions("block_key").write.mode("overwrite").partitionBy("bucket").parquet(path)


def load_blocks(spark: SparkSession, path: str, block_keys: list[str] | None = None, buckets: int = 64) -> DataFrame:
    """Blocks written by `save_blocks`; given keys are found by their buckets alone."""
    df = spark.read.parquet(path)
    if block_keys is None:
        return df
    keys = spark.createDataFrame([(k,) for k in block_keys], "k string")
    at = [r[0] for r in keys.select(F.pmod(F.xxhash64("k"), F.lit(buckets)).cast("int")).distinct().collect()]
    return df.where(F.col("bucket").isin(at) & F.col("block_key").isin(block_keys))


def save_plan(spark: SparkSession, plan: BlockTree | RoundPlan, path: str) -> None:
    kind = "rounds" if isinstance(plan, RoundPlan) else "tree"
    spark.createDataFrame([(kind, plan.to_json())], "kind string, plan string").coalesce(1).write.mode("overwrite").json(path)


def load_plan(spark: SparkSession, path: str) -> BlockTree | RoundPlan:
    r = spark.read.schema("kind string, plan string").json(path).first()
    return RoundPlan.from_json(r["plan"]) if r["kind"] == "rounds" else BlockTree.from_json(r["plan"])
