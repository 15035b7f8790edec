"""The corpus pipeline: five stages over ``documents``, each written as Parquet and read again as the next one's input."""

from __future__ import annotations

from collections.abc import Callable

import public_tokenizers
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from neargraph.llm import bpe, simhash_dedup, source_mix, suffix_dedup, toxicity
from neargraph.llm.kernels import numbered
from neargraph.llm.queries import VOCABULARY
from neargraph.runtime import Scratch

COLUMNS = ("doc_id", "text", "lang", "source", "n_chars")


def drop_toxic(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """Documents that the toxicity model rejects go; all others stay as they are.

    Null, empty and wordless texts score near 0 and stay; rows without an id and repeated rows are judged by their text like others. Without
    labels of both classes nothing is rejected. An empty table gives an empty one.
    """
    labels = spark.read.parquet(f"{sf_dir}/labels.parquet")
    scored = toxicity.annotate(docs.select(*COLUMNS), labels)
    return scored.where("predicted = 0").select(*COLUMNS)


def by_row(docs: DataFrame, stage: Callable[[DataFrame], DataFrame]) -> DataFrame:
    """``stage`` over the documents, for stages that tell rows apart by id.

    If some row has no id or several rows have the same, rows go by their numbers in order of id (null last) and content, and get
    their ids back, so that each row is a document of its own; one without an id is treated as any other, after those that have one.
    """
    docs = docs.select(*COLUMNS)
    odd = docs.groupBy("doc_id").agg(F.count("*").alias("n")).where("doc_id is null or n > 1")
    if odd.isEmpty():
        return stage(docs).select(*COLUMNS)
    content = [F.xxhash64(*COLUMNS[1:], F.lit(seed)) for seed in (0, 1)]
    rows = numbered(docs.withColumnRenamed("doc_id", "given_id"), [F.col("given_id").asc_nulls_last(), *content], Scratch(docs.sparkSession, "rows"), "doc_id")
    return stage(rows).select(F.col("given_id").alias("doc_id"), *COLUMNS[1:])


def drop_near_copies(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """Of each group of SimHash near-duplicates the document with the smallest id stays; a null id is larger than any other.

    Documents without an id link like others, and one of a group that has no ids stays. Rows that share an id are documents of their
    own: of exact copies one stays, and different texts under one id both stay if they are in different groups.
    """

    def first_of_each(rows: DataFrame) -> DataFrame:
        keep = simhash_dedup.simhash_dedup(rows).where("doc_id = component_id").select("doc_id")
        return rows.join(keep, "doc_id", "left_semi")

    return by_row(docs, first_of_each)


def cut_repeats(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """Passages that stand in an earlier place already are cut; a document that is nothing else goes.

    Documents without an id come after all others; rows that share an id, or have none, are in order of their content's hash. Null, empty
    and short texts stay as they are. An empty table gives an empty one.
    """
    return by_row(docs, suffix_dedup.cut_repeats)


def mix_sources(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """The mix by source: a document stands in it as often as it is taken, each row by itself, with an id, a repeated one or none.

    Null, empty and wordless texts have size 0 and are not taken; a null source is a source of its own, last in order. Of the one document
    that a source takes in part its first words stand. An empty table gives an empty one.
    """
    return by_row(docs, source_mix.apply_mix)


def tokenize(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """Token ids of every document of the mix, as digests beside those of the decoded bytes: one row for each row, null ids as they came.

    Null and empty texts have no ids. An empty table gives an empty result.
    """
    return bpe.bpe_digests(docs, public_tokenizers.path(VOCABULARY), public_tokenizers.PATTERN)


STAGES = [("toxicity", drop_toxic), ("simhash_dedup", drop_near_copies), ("suffix_dedup", cut_repeats), ("source_mix", mix_sources), ("bpe", tokenize)]


def run(spark: SparkSession, sf_dir: str) -> DataFrame:
    """All stages over ``documents`` of a folder."""
    scratch = Scratch(spark, "pipeline")
    docs = spark.read.parquet(f"{sf_dir}/documents.parquet")
    for _, stage in STAGES[:-1]:
        docs = scratch.keep(stage(spark, docs, sf_dir))
    return STAGES[-1][1](spark, docs, sf_dir)


#: The first stage is a trained network, which SQL cannot express; tests hold the stages against brute force instead.
ORACLE_SQL = None
