"""Vector sources: the given tables, other formats, packed binary files, dense ids and derived feature vectors."""

from __future__ import annotations

import struct
from collections.abc import Iterator

import numpy as np
import pyarrow as pa
from pyspark.sql import Column, DataFrame, SparkSession
from pyspark.sql import functions as F

from neargraph.runtime import prepare


def table(spark: SparkSession, sf_dir: str, name: str) -> DataFrame:
    return spark.read.parquet(f"{sf_dir}/{name}.parquet")


def vectors(spark: SparkSession, sf_dir: str, name: str = "embeddings", id_col: str = "vec_id", vec_col: str = "embedding") -> DataFrame:
    """VEC rows of a Parquet table; only the two columns are read."""
    return table(spark, sf_dir, name).select(F.col(id_col).cast("long").alias("id"), F.col(vec_col).alias("vec"))


def read(spark: SparkSession, fmt: str, path: str, id_col: str = "id", vec_col: str = "vec") -> DataFrame:
    """VEC rows from csv, json, orc or parquet; text lists like ``[0.1, 0.2]`` are parsed."""
    if fmt == "csv":
        raw = spark.read.option("header", True).csv(path)
        parts = F.split(F.regexp_replace(vec_col, r"[\[\]\s]", ""), ",")
        return raw.select(F.col(id_col).cast("long").alias("id"), F.transform(parts, lambda v: v.cast("float")).alias("vec"))
    raw = spark.read.schema(f"{id_col} long, {vec_col} array<float>").format(fmt).load(path)
    return raw.select(F.col(id_col).alias("id"), F.col(vec_col).alias("vec"))


def write_packed(path: str, x: np.ndarray) -> None:
    """A file of records, each a 32-bit count and that many 32-bit floats (little-endian)."""
    head = struct.pack("<i", x.shape[1])
    with open(path, "wb") as f:
        for row in np.asarray(x, "<f4"):
            f.write(head + row.tobytes())


def _unpack(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
    for batch in batches:
        for path, content in zip(batch.column(0).to_pylist(), batch.column(1).to_pylist(), strict=True):
            if not content:
                continue
            dim = struct.unpack_from("<i", content)[0]
            rows = np.frombuffer(content, "<i4").reshape(-1, dim + 1)
            if (rows[:, 0] != dim).any():
                raise ValueError(f"records of {path} differ in length")
            x = rows[:, 1:].view("<f4")
            for at in range(0, len(x), 4096):
                part = np.ascontiguousarray(x[at : at + 4096])
                vec = pa.ListArray.from_arrays(np.arange(0, part.size + 1, dim, dtype=np.int32), pa.array(part.ravel(), pa.float32()))
                yield pa.RecordBatch.from_arrays([pa.array([path] * len(part)), pa.array(np.arange(at, at + len(part)), pa.int64()), vec], names=["path", "place", "vec"])


def read_packed(spark: SparkSession, path: str) -> DataFrame:
    """(path, place, vec) of packed files; one file is one task, so large sets come in many files."""
    prepare(spark)
    return spark.read.format("binaryFile").load(path).select("path", "content").mapInArrow(_unpack, "path string, place long, vec array<float>")


def validate(vecs: DataFrame, dim: int | None = None) -> dict[str, int]:
    """One aggregate over VEC rows; raises on null, non-finite or differently long vectors, null or repeated ids."""
    v = F.col("vec")
    row = vecs.agg(
        F.count("*").alias("n"),
        F.min(F.size(v)).alias("low"),
        F.max(F.size(v)).alias("high"),
        F.sum((v.isNull() | F.col("id").isNull() | F.exists(v, lambda x: x.isNull() | F.isnan(x) | (F.abs(x) == float("inf")))).cast("long")).alias("bad"),
        F.count_distinct("id").alias("ids"),
    ).first()
    if row.n and (row.bad or row.low != row.high or row.ids != row.n or (dim is not None and row.low != dim)):
        raise ValueError(f"invalid vectors: {row.asDict()}")
    return {"n": row.n, "dim": row.low or 0}


def dense_ids(df: DataFrame, keys: list[str]) -> DataFrame:
    """Adds ``id`` 0..N-1 in the order of the keys: ranges are sorted apart and the sizes of the ranges before are added. Equal keys must not occur."""
    spark = df.sparkSession
    parts = int(spark.conf.get("spark.sql.shuffle.partitions"))
    ordered = df.repartitionByRange(parts, *keys).sortWithinPartitions(*keys).withColumn("part", F.spark_partition_id())
    from neargraph.runtime import Scratch

    ordered = Scratch(spark, "ids").keep(ordered.withColumn("place", F.monotonically_increasing_id() - F.shiftleft(F.col("part").cast("long"), 33)))
    offsets, total = [], 0
    for row in ordered.groupBy("part").agg(F.count("*").alias("n")).orderBy("part").collect():  # one row for each partition
        offsets.append((row.part, total))
        total += row.n
    if not offsets:
        return ordered.withColumn("id", F.col("place")).drop("part", "place")
    side = spark.createDataFrame(offsets, "part int, before long")
    return ordered.join(F.broadcast(side), "part").withColumn("id", F.col("place") + F.col("before")).drop("part", "place", "before")


def zscores(df: DataFrame, columns: list[str]) -> DataFrame:
    """Adds ``z_<column>``; a constant column gives 0."""
    stats = df.agg(*(f(c).alias(f"{n}_{c}") for c in columns for n, f in (("m", F.avg), ("s", F.stddev_pop))))
    joined = df.crossJoin(F.broadcast(stats))  # one row
    for c in columns:
        joined = joined.withColumn(f"z_{c}", F.when(F.col(f"s_{c}") > 0, (F.col(c) - F.col(f"m_{c}")) / F.col(f"s_{c}")).otherwise(0.0))
    return joined.drop(*(f"{n}_{c}" for c in columns for n in ("m", "s")))


LINE_FEATURES = ["l_quantity", "l_extendedprice", "l_discount", "l_tax", "ship_day"]


def lineitem_features(spark: SparkSession, sf_dir: str) -> DataFrame:
    line = table(spark, sf_dir, "lineitem").withColumn("ship_day", F.datediff("l_shipdate", F.lit("1992-01-01").cast("date")).cast("double"))
    return line.select("l_orderkey", "l_linenumber", *(F.col(c).cast("double").alias(c) for c in LINE_FEATURES))


def lineitem_vectors(spark: SparkSession, sf_dir: str) -> DataFrame:
    """VEC rows of five z-scored features, ids in the order of all key and feature columns."""
    rows = zscores(lineitem_features(spark, sf_dir), LINE_FEATURES)
    rows = dense_ids(rows, ["l_orderkey", "l_linenumber", *LINE_FEATURES])
    return rows.select("id", F.array(*(F.col(f"z_{c}").cast("float") for c in LINE_FEATURES)).alias("vec"))


def gram_counts(rows: DataFrame, id_col: str, text: Column, dim: int) -> DataFrame:
    """(id, bucket, n): hashed character 3-grams of a lower-cased text; bucket = (c1*961 + c2*31 + c3) mod dim."""
    codes = F.transform(F.split(F.lower(F.coalesce(text, F.lit(""))), ""), lambda c: F.ascii(c).cast("long"))
    rows = rows.select(F.col(id_col).alias("id"), F.filter(codes, lambda c: c > 0).alias("c"))
    n = F.greatest(F.size("c") - 2, F.lit(0))
    pairs = F.zip_with(F.slice("c", F.lit(1), n), F.slice("c", F.lit(2), n), lambda a, b: a * 961 + b * 31)
    grams = F.zip_with(pairs, F.slice("c", F.lit(3), n), lambda a, b: (a + b) % dim)
    return rows.select("id", F.explode(grams).alias("bucket")).groupBy("id", "bucket").agg(F.count("*").alias("n"))


def gram_vectors(rows: DataFrame, id_col: str, text_col: str, dim: int) -> DataFrame:
    """VEC rows of unit length from character 3-grams, counted as by ``gram_counts``; texts below three characters give zero vectors."""
    prepare(rows.sparkSession)

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in batches:
            x = np.zeros((batch.num_rows, dim))
            for i, text in enumerate(batch.column(1)):
                c = np.frombuffer(text.as_py().encode("utf-32-le"), "<u4").astype(np.int64)
                c = c[c > 0]
                if len(c) > 2:
                    x[i] = np.bincount((c[:-2] * 961 + c[1:-1] * 31 + c[2:]) % dim, minlength=dim)
            size = np.sqrt((x * x).sum(axis=1, keepdims=True))
            x = np.divide(x, size, out=x, where=size > 0).astype(np.float32)
            vec = pa.ListArray.from_arrays(np.arange(0, x.size + 1, dim, dtype=np.int32), pa.array(x.ravel(), pa.float32()))
            yield pa.RecordBatch.from_arrays([batch.column(0), vec], names=["id", "vec"])

    texts = rows.select(F.col(id_col).cast("long").alias("id"), F.lower(F.coalesce(F.col(text_col), F.lit(""))).alias("text"))
    return texts.mapInArrow(run, "id long, vec array<float>")


def pair_means(vecs: DataFrame, count: int, n: int) -> DataFrame:
    """QRY rows: means of two vectors each, q_j of v_(j mod n) and v_((7919 j + 13) mod n)."""
    j = vecs.sparkSession.range(count).select(F.col("id").alias("qid"), (F.col("id") % n).alias("a"), ((F.col("id") * 7919 + 13) % n).alias("b"))
    x, y = vecs.select(F.col("id").alias("a"), F.col("vec").alias("va")), vecs.select(F.col("id").alias("b"), F.col("vec").alias("vb"))
    return j.join(x, "a").join(y, "b").select("qid", F.zip_with("va", "vb", lambda s, t: ((s + t) / 2).cast("float")).alias("vec"))
