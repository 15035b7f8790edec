"""Mixing sources to target weights by pivotal rounding in a distributed reduction tree.

Targets fill up by weight until they meet their ceiling. A source at ``r`` times its size takes ``floor(r)`` whole copies of
each document and a fraction of one more. The fractions are settled by pairs: word mass moves at random between two
documents, in amounts that leave every expectation as it is, until one of the two holds no copy or a whole one. The sum of
the words never changes, so a source meets its target whatever the draws. Small groups settle by themselves and hand one
unsettled document each to the next level of the tree, until a source has one left, which gives the words that remain.
"""

from __future__ import annotations

import numpy as np
import pandas as pd
from pyspark.sql import DataFrame, Window
from pyspark.sql import functions as F

from neargraph.runtime import Scratch

WORD = r"[^\x20\x09-\x0D]+"
WEIGHTS = (5.0, 2.0, 1.0)
SHARE = 1.5
CEILING = 2.0
GROUP_ROWS = 512
FAN_IN = 64


def word_count(text):
    """Number of ASCII-space separated words of a column; null: 0."""
    return F.coalesce(F.regexp_count(text, F.lit(WORD)), F.lit(0)).cast("long")


def source_targets(sized: DataFrame, scratch: Scratch, *, weights=WEIGHTS, share: float = SHARE, ceiling: float = CEILING) -> DataFrame:
    """``(source, size)`` -> one row for each source: ``(source, source_size, target)``.

    Weights go round the sources in order of code point, null last. ``share`` times all words are dealt by weight; a target
    stops at ``ceiling`` times its source's size and the rest is dealt again among the others.
    """
    totals = sized.groupBy("source").agg(F.sum("size").alias("source_size"), F.count("*").alias("n_docs"))
    place = F.row_number().over(Window.orderBy(F.col("source").isNull(), "source")) - 1  # one row for each source
    weight = F.element_at(F.array(*map(F.lit, weights)), (place % len(weights) + 1).cast("int"))
    table = scratch.keep(totals.withColumn("weight", weight))
    whole = float(table.agg(F.sum("source_size")).first()[0] or 0) * share
    level = 0.0  # words for each unit of weight
    while True:
        stops = ceiling * F.col("source_size") <= level * F.col("weight")
        full, open_weight = table.agg(F.sum(F.when(stops, ceiling * F.col("source_size")).otherwise(0.0)), F.sum(F.when(stops, 0.0).otherwise(F.col("weight")))).first()
        if not open_weight:
            break
        new = (whole - full) / open_weight
        if new <= level * (1 + 1e-15):
            break
        level = new
    return table.withColumn("target", F.least(ceiling * F.col("source_size").cast("double"), F.lit(level) * F.col("weight"))).drop("weight")


def _uniform(a: int, b: int, seed: int) -> float:
    """Deterministic draw in [0, 1) for a pair of documents."""
    x = (a * 0x9E3779B97F4A7C15 + b * 0xC2B2AE3D27D4EB4F + seed * 0x165667B19E3779F9 + 0x27D4EB2F165667C5) & 0xFFFFFFFFFFFFFFFF
    for shift, factor in ((30, 0xBF58476D1CE4E5B9), (27, 0x94D049BB133111EB)):
        x = ((x ^ (x >> shift)) * factor) & 0xFFFFFFFFFFFFFFFF
    return ((x ^ (x >> 31)) >> 11) / float(1 << 53)


def settle(keys: np.ndarray, sizes: np.ndarray, mass: np.ndarray, seed: int) -> tuple[np.ndarray, int]:
    """Pivotal rounding of word masses ``0 <= mass <= size`` in the given order. Returns the masses and the one left open (-1: none)."""
    mass = mass.astype(np.float64).copy()
    held = -1
    for i in range(len(keys)):
        if mass[i] <= 0 or mass[i] >= sizes[i]:
            continue
        if held < 0:
            held = i
            continue
        x, y, a, b = mass[held], mass[i], float(sizes[held]), float(sizes[i])
        to_i, to_held = min(x, b - y), min(y, a - x)  # most that can move either way
        if _uniform(int(keys[held]), int(keys[i]), seed) * (to_i + to_held) < to_held:  # moves to i with probability to_held / both
            x, y = x - to_i, y + to_i
            x, y = (0.0, y) if to_i == mass[held] else (x, b)
        else:
            x, y = x + to_held, y - to_held
            x, y = (x, 0.0) if to_held == mass[i] else (a, y)
        mass[held], mass[i] = x, y
        open_held, open_i = 0 < x < a, 0 < y < b
        held = held if open_held else i if open_i else -1
    return mass, held


_ROWS = "source string, doc_id long, row_key long, size long, copies long, mass double, bucket long, settled boolean"


def _settle_group(pdf: pd.DataFrame, seed: int, last: bool) -> pd.DataFrame:
    pdf = pdf.sort_values(["row_key", "doc_id", "size"], kind="stable", na_position="last").reset_index(drop=True)
    mass, held = settle(pdf["row_key"].to_numpy(), pdf["size"].to_numpy(), pdf["mass"].to_numpy(), seed)
    pdf["mass"] = mass
    pdf["settled"] = True
    if held >= 0:
        if last:
            pdf.loc[held, "mass"] = np.round(mass[held])
        else:
            pdf.loc[held, "settled"] = False
    return pdf


def _settler(seed: int, last: bool):
    return lambda pdf: _settle_group(pdf, seed, last)


def mix(docs: DataFrame, *, seed: int = 7, weights=WEIGHTS, share: float = SHARE, ceiling: float = CEILING, group_rows: int = GROUP_ROWS) -> DataFrame:
    """``documents`` -> ``(doc_id, size, source_size, target, taken)``, one row for each input row.

    ``taken`` counts the words that the mix takes of a document, repeats counted: whole copies, but for one document of each
    source, which gives the words that remain. Null texts have size 0 and are never taken; a null source is a source of its
    own, last in order; repeated rows are dealt with each by itself. Draws depend on ids, texts and the seed alone, so reruns
    agree. An empty table gives an empty result. Other columns than doc_id, text and source are not read.
    """
    spark = docs.sparkSession
    scratch = Scratch(spark, "mix")
    sized = scratch.keep(docs.select(F.col("doc_id").cast("long").alias("doc_id"), F.col("source").cast("string").alias("source"), word_count(F.col("text")).alias("size"), F.xxhash64("text").alias("text_hash")))
    targets = scratch.keep(source_targets(sized, scratch, weights=weights, share=share, ceiling=ceiling))
    most = targets.agg(F.max("n_docs")).first()[0] or 0
    small = targets.select(F.col("source").alias("s"), "source_size", "target", "n_docs")
    rate = F.when(F.col("source_size") > 0, F.col("target") / F.col("source_size")).otherwise(0.0)
    row_key = F.xxhash64("doc_id", "text_hash", F.lit(seed))  # rows without an id differ by their texts
    rows = sized.join(small, sized.source.eqNullSafe(small.s)).withColumn("rate", rate)
    groups = F.greatest(F.lit(1), F.ceil(F.col("n_docs") / group_rows)).cast("long")
    rows = rows.select("source", "doc_id", row_key.alias("row_key"), "size", F.floor("rate").cast("long").alias("copies"), ((F.col("rate") - F.floor("rate")) * F.col("size")).alias("mass"), F.pmod(F.xxhash64("doc_id", "text_hash", F.lit(seed + 1)), groups).alias("bucket"), F.lit(False).alias("settled"))
    done: list[DataFrame] = []
    left, width, level = rows, max(1, -(-most // group_rows)), 0
    while True:
        last = width == 1
        out = scratch.keep(left.groupBy("source", "bucket").applyInPandas(_settler(seed + 101 * level, last), _ROWS))
        done.append(out.where("settled") if not last else out)
        if last:
            break
        left = out.where("not settled").withColumn("bucket", F.floor(F.col("bucket") / FAN_IN).cast("long"))
        width, level = -(-width // FAN_IN), level + 1
    all_rows = done[0]
    for more in done[1:]:
        all_rows = all_rows.unionByName(more)
    taken = (F.col("copies") * F.col("size") + F.round("mass").cast("long")).alias("taken")
    return all_rows.join(small, all_rows.source.eqNullSafe(small.s)).select("doc_id", "size", "source_size", "target", taken)


def apply_mix(docs: DataFrame, **options) -> DataFrame:
    """The mixed documents themselves: every copy a row, and of the one partial document of a source its first words.

    Documents with a null id cannot be told apart and are left out here; ``mix`` still counts them.
    """
    columns = docs.columns
    taken = mix(docs, **options).where("taken > 0").groupBy(F.col("doc_id").alias("mix_id")).agg(F.max("taken").alias("mix_taken"), F.max("size").alias("mix_size"))
    joined = docs.join(taken, docs.doc_id == taken.mix_id)
    whole = F.floor(F.col("mix_taken") / F.col("mix_size")).cast("int")
    rest = F.col("mix_taken") - whole * F.col("mix_size")
    # words with the white space before them, so that the part is a prefix of the text
    part = F.array_join(F.slice(F.regexp_extract_all("text", F.lit(rf"[\x20\x09-\x0D]*{WORD}"), F.lit(0)), 1, F.col("mix_rest").cast("int")), "")
    rows = joined.withColumn("mix_rest", rest).withColumn("mix_copy", F.explode(F.sequence(F.lit(1), whole + F.when(rest > 0, 1).otherwise(0))))
    cut = F.col("mix_copy") > whole
    rows = rows.withColumn("text", F.when(cut, part).otherwise(F.col("text"))).withColumn("n_chars", F.when(cut, F.length("text").cast("long")).otherwise(F.col("n_chars")))
    return rows.select(*columns)
