"""Quality selection by importance resampling with hashed n-gram models.

Two generative models of hashed word unigrams and bigrams are counted: of the target texts (a bounded sample of those labelled good)
and of all raw texts. A document's weight is the logarithm of the ratio of its probabilities under the two; adding Gumbel noise to the
weights and keeping the k largest keys draws k documents without replacement in proportion to the ratios. The k-th largest key
is found by counting in ever finer bins.
"""

from __future__ import annotations

import math
import zlib
from collections.abc import Iterator

import numpy as np
import pyarrow as pa
import xxhash
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from neargraph.llm.kernels import ascii_words, documents_of, numbered, pieces, record, resident
from neargraph.runtime import Scratch, prepare

BUCKETS = 10_000
#: Most target texts that the target model is counted from, in the order of a hash of the id.
TARGET_TEXTS = 50_000
#: Texts that a kernel holds at a time.
BATCH_TEXTS = 1024


class Hasher:
    """Bucket counts of texts; remembers the hashes of up to ``limit`` words."""

    def __init__(self, limit: int = 150_000) -> None:
        self.limit, self.known = limit, {}

    def buckets(self, text: str | None) -> np.ndarray:
        words = ascii_words(text, lower=True)
        if not words:
            return np.zeros(0, np.int64)
        known = self.known
        try:
            h = np.fromiter(map(known.__getitem__, words), np.uint64, len(words))
        except KeyError:
            if len(known) > self.limit:
                for w in list(known)[self.limit // 2 :]:
                    del known[w]
            for w in words:
                if w not in known:
                    known[w] = zlib.crc32(w) * 0x9E3779B97F4A7C15 & 0xFFFFFFFFFFFFFFFF
            h = np.fromiter(map(known.__getitem__, words), np.uint64, len(words))
        pairs = (h[:-1] * np.uint64(0xC2B2AE3D27D4EB4F) + h[1:]) ^ np.uint64(0x165667B19E3779F9)
        mixed = np.concatenate([h, pairs])
        mixed ^= mixed >> np.uint64(31)
        return (mixed % np.uint64(BUCKETS)).astype(np.int64)


def _count_batches(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
    """One row for each bucket and task: counts in all texts and in the target texts."""
    hasher = resident("grams", None, Hasher)
    counts = np.zeros((2, BUCKETS), np.int64)
    for whole in batches:
        for at in range(0, whole.num_rows, BATCH_TEXTS):
            batch = whole.slice(at, BATCH_TEXTS)
            for text, good in zip(batch.column(0).to_pylist(), batch.column(1).to_pylist(), strict=True):
                own = np.bincount(hasher.buckets(text), minlength=BUCKETS)
                counts[0] += own
                if good:
                    counts[1] += own
    schema = pa.schema([("bucket", pa.int64()), ("raw", pa.int64()), ("target", pa.int64())])
    full = np.flatnonzero(counts[0])
    yield record(schema, full, counts[0][full], counts[1][full])


def _weigh_batches(batches: Iterator[pa.RecordBatch], shared) -> Iterator[pa.RecordBatch]:
    ratio, hasher = shared.value, resident("grams", None, Hasher)
    schema = pa.schema([("doc_id", pa.int64()), ("n_grams", pa.int64()), ("log_ratio", pa.float64()), ("text_hash", pa.int64())])
    for ids, texts in pieces(batches, 1_000_000):
        n, weights, hashes = [], [], []
        for text in texts:
            own = hasher.buckets(text)
            n.append(len(own)), weights.append(float(ratio[own].sum()))
            hashes.append(xxhash.xxh3_64_intdigest((text or "").encode("utf-8", "surrogatepass")) - (1 << 63))
        yield record(schema, ids, n, weights, hashes)


def log_ratios(raw: np.ndarray, target: np.ndarray) -> np.ndarray:
    """Logarithm of target over raw probability for each bucket, one count added to each."""
    p = (target + 1) / (target.sum() + len(target))
    q = (raw + 1) / (raw.sum() + len(raw))
    return np.log(p) - np.log(q)


def kth_largest(keys: DataFrame, column: str, k: int, *, bins: int = 4096, rounds: int = 8) -> float:
    """The k-th largest value of a finite double column: counts in bins of the range that must hold it, until it is one value."""
    low, high = keys.agg(F.min(column), F.max(column)).first()
    above = 0
    for _ in range(rounds):
        if low >= high:
            break
        width = (high - low) / bins
        if low + width == low:
            break
        place = F.least(F.lit(bins - 1), F.floor((F.col(column) - low) / width)).cast("int")
        rows = keys.where((F.col(column) >= low) & (F.col(column) <= high)).groupBy(place.alias("bin")).agg(F.count("*").alias("n"), F.min(column).alias("low"), F.max(column).alias("high")).orderBy(F.desc("bin")).collect()
        for row in rows:  # at most one row for each bin
            if above + row.n >= k:
                low, high = row.low, row.high
                break
            above += row.n
    return low


def importance_sample(docs: DataFrame, labels: DataFrame, *, keep: float | None = None, target_texts: int = TARGET_TEXTS, seed: int = 5) -> DataFrame:
    """``documents``, ``labels`` -> ``(doc_id, n_grams, log_ratio, gumbel_key, selected)``, one row for each input row.

    The target model counts at most ``target_texts`` texts labelled ``quality = 1``, the raw model all texts. ``log_ratio`` is the sum of
    the log ratios of a text's n-grams; exactly ceil(keep * rows) rows are selected, those of the largest keys. ``keep`` defaults to the share
    of good ones among the labelled documents (1 without any). Null, empty and wordless texts have ratio 1. The noise depends on id, text
    and seed alone, so reruns agree; rows that repeat id and text share their key, and if the cut falls between them some are
    selected and some are not. Other ties go to the smaller id, null last. Without target texts every ratio is 1 and the sample is an even
    one. An empty table gives an empty result. A document labelled both good and bad counts as good.
    """
    spark = prepare(docs.sparkSession)
    scratch = Scratch(spark, "importance")
    texts = documents_of(docs)
    marks = labels.select(F.col("doc_id").cast("long").alias("label_id"), F.col("quality").cast("int").alias("quality")).where("quality in (0, 1) and label_id is not null")
    marks = marks.groupBy("label_id").agg(F.max("quality").alias("quality"))
    if keep is None:
        keep = marks.agg(F.avg("quality")).first()[0]
        keep = 1.0 if keep is None else float(keep)
    good = marks.where("quality = 1").select("label_id").join(texts.select("doc_id"), F.col("label_id") == F.col("doc_id"), "left_semi")
    good = good.orderBy(F.xxhash64("label_id"), "label_id").limit(target_texts)  # a broadcast of at most so many ids
    marked = texts.join(F.broadcast(good), texts.doc_id == good.label_id, "left").select("text", F.col("label_id").isNotNull().alias("good"))
    counts = marked.mapInArrow(_count_batches, "bucket long, raw long, target long").groupBy("bucket").agg(F.sum("raw").alias("raw"), F.sum("target").alias("target")).toPandas()  # at most BUCKETS rows
    raw, target = np.zeros(BUCKETS), np.zeros(BUCKETS)
    raw[counts["bucket"]], target[counts["bucket"]] = counts["raw"], counts["target"]
    shared = spark.sparkContext.broadcast(log_ratios(raw, target) if target.sum() else np.zeros(BUCKETS))
    weighed = texts.mapInArrow(lambda it: _weigh_batches(it, shared), "doc_id long, n_grams long, log_ratio double, text_hash long")
    uniform = (F.pmod(F.xxhash64("doc_id", "text_hash", F.lit(seed)), F.lit(1 << 52)).cast("double") + 0.5) / float(1 << 52)
    keyed = scratch.keep(weighed.withColumn("gumbel_key", F.col("log_ratio") - F.log(-F.log(uniform))))
    n = keyed.count()
    columns = ("doc_id", "n_grams", "log_ratio", "gumbel_key")
    k = math.ceil(keep * n)
    if not k:
        return keyed.select(*columns, F.lit(False).alias("selected"))
    cut = kth_largest(keyed, "gumbel_key", k)
    above = keyed.where(F.col("gumbel_key") > cut).count()
    tied = numbered(keyed.where(F.col("gumbel_key") == cut), [F.col("doc_id").asc_nulls_last(), "text_hash"], scratch)
    apart = keyed.where(F.col("gumbel_key") != cut).select(*columns, (F.col("gumbel_key") > cut).alias("selected"))
    return apart.unionByName(tied.select(*columns, (F.col("number") < k - above).alias("selected")))
