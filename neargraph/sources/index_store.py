"""A stored index: vectors and lists in one Parquet table, partitioned by shard and sorted by id, and a small table about it."""

from __future__ import annotations

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F


def save(index: DataFrame, path: str, **about: str) -> None:
    index.repartition("shard_id").sortWithinPartitions("shard_id", "id").write.partitionBy("shard_id").parquet(f"{path}/graph")
    spark = index.sparkSession
    stats = spark.read.parquet(f"{path}/graph").agg(F.count("*").alias("n"), F.max(F.size("vec")).alias("dim"), F.max(F.size("nbrs")).alias("d"), F.count_distinct("shard_id").alias("shards"))
    entries = [F.lit(x) for kv in sorted(about.items()) for x in kv]
    stats.withColumn("about", F.create_map(*entries) if entries else F.create_map().cast("map<string,string>")).write.json(f"{path}/about")


def open_index(spark: SparkSession, path: str) -> DataFrame:
    """A filter on ``shard_id`` reads only those folders."""
    return spark.read.schema("id long, vec array<float>, nbrs array<long>, shard_id int").parquet(f"{path}/graph").select("shard_id", "id", "vec", "nbrs")


def about(spark: SparkSession, path: str) -> dict:
    return spark.read.json(f"{path}/about").first().asDict(recursive=True)


def missing_shards(spark: SparkSession, path: str, shards: int) -> list[int]:
    """Shards not yet written, so that a build that was stopped can go on."""
    try:
        done = {r.shard_id for r in open_index(spark, path).select("shard_id").distinct().collect()}
    except Exception as e:
        if "PATH_NOT_FOUND" not in str(e):
            raise
        done = set()
    return [s for s in range(shards) if s not in done]


def save_bucketed(adj: DataFrame, name: str, buckets: int) -> None:
    """Lists as a bucketed table, so that joins on ``id`` move the other side only."""
    adj.write.bucketBy(buckets, "id").sortBy("id").mode("overwrite").saveAsTable(name)
