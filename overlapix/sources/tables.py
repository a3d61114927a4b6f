"""The given tables and the set collections made of them."""

from __future__ import annotations

from collections.abc import Callable

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from overlapix.operators import sets
from overlapix.sources.formats import scratch


def load(spark: SparkSession, sf_dir: str, name: str) -> DataFrame:
    return spark.read.parquet(f"{sf_dir}/{name}.parquet")


#: Tables of fewer bytes are as quick in one task.
SPREAD_BYTES = 4 << 20


def spread(df: DataFrame) -> DataFrame:
    """``df`` over all cores where its scan has fewer tasks than they are: a file of
    one row group is one task.  Never so where there is more than a task a core."""
    cores = df.sparkSession.sparkContext.defaultParallelism
    plan = df._jdf.queryExecution()
    if int(str(plan.optimizedPlan().stats().sizeInBytes())) < SPREAD_BYTES or df.rdd.getNumPartitions() >= 2 * cores:
        return df
    return df.repartition(cores)


def kept(df: DataFrame, label: str = "kept") -> DataFrame:
    """``df`` written once to the shared folder, for plans that read it several times."""
    path = scratch(df.sparkSession, label)
    df.write.parquet(path)
    return df.sparkSession.read.schema(df.schema).parquet(path)


def _text(table: str, key: str, column: str = "text", k: int = 1) -> Callable[[SparkSession, str], DataFrame]:
    def build(spark: SparkSession, d: str) -> DataFrame:
        rows = spread(load(spark, d, table).select(key, column))
        return sets.shingle_sets(rows, key, column, k) if k > 1 else sets.word_sets(rows, key, column)

    return build


def _basket(build: Callable[[SparkSession, str], DataFrame]) -> Callable[[SparkSession, str], DataFrame]:
    return lambda spark, d: sets.incidence_sets(build(spark, d), "id", "token")


def bought(spark: SparkSession, d: str) -> DataFrame:
    lines, orders = load(spark, d, "lineitem"), load(spark, d, "orders")
    return lines.join(orders, lines.l_orderkey == orders.o_orderkey).select(F.col("o_custkey").alias("id"), F.col("l_partkey").cast("string").alias("token"), F.col("l_quantity").alias("w"))


def hours(events: DataFrame) -> DataFrame:
    return events.select(F.col("user_id").alias("id"), F.date_format("ts", "yyyy-MM-dd HH").alias("token"))


def _words_of(spark: SparkSession, d: str, key) -> DataFrame:
    return load(spark, d, "conversations").select(key.alias("id"), F.explode(sets.tokens(F.col("text"))).alias("token"))


COLLECTIONS: dict[str, Callable[[SparkSession, str], DataFrame]] = {
    "docs_w": _text("documents", "doc_id"),
    "docs_s3": _text("documents", "doc_id", k=3),
    "pages_w": lambda spark, d: sets.html_sets(spread(load(spark, d, "pages").select("page_id", "html")), "page_id", "html"),
    "conv_w": _basket(lambda spark, d: _words_of(spark, d, F.col("conv_id"))),
    "turn_w": _basket(lambda spark, d: _words_of(spark, d, F.col("conv_id") * 1000 + F.col("turn"))),
    "cust_parts": _basket(bought),
    "order_parts": _basket(lambda spark, d: load(spark, d, "lineitem").select(F.col("l_orderkey").alias("id"), F.col("l_partkey").cast("string").alias("token"))),
    "part_supps": _basket(lambda spark, d: load(spark, d, "lineitem").select(F.col("l_partkey").alias("id"), F.col("l_suppkey").cast("string").alias("token"))),
    "user_hours": _basket(lambda spark, d: hours(load(spark, d, "events"))),
    "emb_bin": lambda spark, d: sets.binarize(load(spark, d, "embeddings"), "vec_id", "embedding"),
    "bench_w": _text("benchmark", "item_id"),
    "bench_s3": _text("benchmark", "item_id", k=3),
}


def collection(spark: SparkSession, sf_dir: str, name: str) -> DataFrame:
    """``(id, elems, f)``."""
    return COLLECTIONS[name](spark, sf_dir)
