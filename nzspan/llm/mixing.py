"""Mixing sources to target weights by pivotal dependent rounding.

Every source gets a share of the words of the whole corpus by its weight, held under a cap of so
many repeats. A document of a source is then wanted rate = target / size times: floor(rate) times for
certain, and once more with the probability that is left. Pivotal rounding decides on these
fractions: two documents exchange mass, measured in words, until one of them is whole; so a source
takes its target to within one document, and each document is wanted as often as it should be on average.
Blocks of a source round on their own and leave one undecided document each; these meet in
blocks of blocks, up to one document for each source.

Edge cases: a null text has no words; a null source is a source of its own, the last; documents without words are
never taken; an empty table gives an empty mix; other columns of the input are left aside.
"""

from __future__ import annotations

import numpy as np
import pandas as pd
from pyspark.sql import DataFrame, SparkSession, Window
from pyspark.sql import functions as F

from nzspan.session import ship, written

from . import common

#: Documents in a block, and blocks in a block of the next level.
FANOUT = 1024


def source_targets(sizes: DataFrame, max_repeats: float = 3.0, weight_cycle: int = 3) -> DataFrame:
    """(source, source_size, n_docs, source_rank, weight, target) from (source, size).

    Weights run 1..weight_cycle over the sources in code point order, null last. Targets share the words of
    all sources by weight; a target over max_repeats times its source's size is held there and
    what it leaves is shared anew. The cap of source k binds if its ratio cap / weight lies under the level
    that the sources from k on would reach, with ratios in ascending order.
    """
    per = sizes.groupBy("source").agg(F.sum("size").alias("source_size"), F.count(F.lit(1)).alias("n_docs"))
    by_name = Window.orderBy(F.col("source").asc_nulls_last())
    per = per.withColumn("source_rank", F.row_number().over(by_name)).withColumn("weight", (F.col("source_rank") - 1) % weight_cycle + 1)
    per = per.withColumn("cap", F.col("source_size") * max_repeats)
    ratio = Window.orderBy(F.col("cap") / F.col("weight"), "source_rank")
    everything = Window.partitionBy()
    before = F.coalesce(F.sum("cap").over(ratio.rowsBetween(Window.unboundedPreceding, -1)), F.lit(0.0))
    left = F.sum("weight").over(ratio.rowsBetween(0, Window.unboundedFollowing))
    per = per.withColumn("level", (F.sum("source_size").over(everything) - before) / left)
    per = per.withColumn("bound", F.col("cap") <= F.col("level") * F.col("weight"))
    shared = F.max(F.when(~F.col("bound"), F.col("level"))).over(everything)
    target = F.when(F.col("bound"), F.col("cap")).otherwise(F.least("cap", shared * F.col("weight")))
    return per.withColumn("target", target.cast("double")).select("source", "source_size", "n_docs", "source_rank", "weight", "target")


def pivot(size: np.ndarray, share: np.ndarray, chance: np.ndarray) -> np.ndarray:
    """Round shares to 0 or 1 but for one at most; the sum of size * share stays.

    Documents come one after the other; the one that is still open meets the next. chance[j] in [0, 1) decides the
    meeting with document j.
    """
    out = share.astype(float).copy()
    open_at = -1
    for j in range(len(out)):
        if not 0.0 < out[j] < 1.0:
            continue
        if open_at < 0:
            open_at = j
            continue
        a, b, p, q = size[open_at], size[j], out[open_at], out[j]
        gives, takes = min(a * (1 - p), b * q), min(a * p, b * (1 - q))  # words towards the open one, or away
        if chance[j] * (gives + takes) < takes:
            whole_open, whole_next = a * (1 - p) <= b * q, a * (1 - p) >= b * q
            p, q = p + gives / a, q - gives / b
            p, q = (1.0 if whole_open else p), (0.0 if whole_next else q)
        else:
            whole_open, whole_next = a * p <= b * (1 - q), a * p >= b * (1 - q)
            p, q = p - takes / a, q + takes / b
            p, q = (0.0 if whole_open else p), (1.0 if whole_next else q)
        out[open_at], out[j] = p, q
        if 0.0 < p < 1.0:
            continue
        open_at = j if 0.0 < q < 1.0 else -1
    return out


def _round_block(rows: pd.DataFrame) -> pd.DataFrame:
    rows = rows.sort_values(["turn", "doc_id", "size"], kind="stable", na_position="last")
    rows["share"] = pivot(rows["size"].to_numpy(), rows["share"].to_numpy(), rows["chance"].to_numpy())
    return rows


def mix(documents: DataFrame, max_repeats: float = 3.0, weight_cycle: int = 3, seed: int = 42, fanout: int = FANOUT) -> DataFrame:
    """(doc_id, source, size, source_size, target, rate, copies, taken) for every row of documents(doc_id, text, source).

    copies is how often the mix holds the document, taken = copies * size. Chances are hashes of seed and doc_id, so that
    reruns agree, however the rows lie.
    """
    spark = documents.sparkSession
    ship(spark)
    sizes = written(documents.select("doc_id", "source", common.word_count(F.col("text")).alias("size")), "mix-sizes")
    sources = written(source_targets(sizes, max_repeats, weight_cycle), "mix-sources")
    rated = sizes.join(sources, sizes["source"].eqNullSafe(sources["source"])).drop(sources["source"])
    rated = rated.withColumn("rate", F.when(F.col("source_size") > 0, F.col("target") / F.col("source_size")).otherwise(0.0))
    rated = rated.withColumn("share", F.when(F.col("size") > 0, F.col("rate") - F.floor("rate")).otherwise(0.0))
    uniform = lambda salt: F.shiftrightunsigned(F.xxhash64(F.lit(seed), F.lit(salt), "doc_id"), 11) / F.lit(float(2**53))
    block = F.pmod(F.xxhash64(F.lit(seed), F.lit("block"), "doc_id"), F.ceil(F.col("n_docs") / fanout))
    level = rated.select("doc_id", "source_rank", block.alias("block"), "size", "share", F.xxhash64(F.lit(seed), F.lit("turn"), "doc_id").alias("turn"), uniform("chance").alias("chance"))
    blocks = (sources.agg(F.max(F.ceil(F.col("n_docs") / fanout))).first()[0] or 1) if sources.head(1) else 1
    fixed = rated.where(F.col("share") == 0.0).select("doc_id", "source_rank", "size", F.lit(0.0).alias("share"))
    level, settled, depth = level.where(F.col("share") > 0.0), [fixed], 0
    while True:
        level = written(level.groupBy("source_rank", "block").applyInPandas(_round_block, level.schema), f"mix-level{depth}")
        is_open = (F.col("share") > 0.0) & (F.col("share") < 1.0)
        settled.append(level.where(~is_open).select("doc_id", "source_rank", "size", "share"))
        level = level.where(is_open)
        if blocks <= 1:
            break
        blocks, depth = -(-blocks // fanout), depth + 1
        level = level.withColumn("block", F.floor(F.col("block") / fanout))
    last = level.select("doc_id", "source_rank", "size", (uniform("last") < F.col("share")).cast("double").alias("share"))
    rounded = last
    for part in settled:
        rounded = rounded.unionByName(part)
    out = rounded.join(sources, "source_rank").withColumn("rate", F.when(F.col("source_size") > 0, F.col("target") / F.col("source_size")).otherwise(0.0))
    copies = F.when(F.col("size") > 0, F.floor("rate") + F.col("share").cast("long")).otherwise(0).cast("long")
    return out.withColumn("copies", copies).select("doc_id", "source", "size", "source_size", "target", "rate", "copies", (F.col("copies") * F.col("size")).alias("taken"))


def op1_mixing(spark: SparkSession, sf_dir: str) -> DataFrame:
    """The mix of all documents: doc_id, size, source_size, target, taken, copies.

    Null and empty texts have size 0 and are never taken. Rows without a source are a source, the last; repeated rows are rounded
    each. An empty table gives no rows. Other columns are left aside.
    """
    mixed = mix(common.table(spark, sf_dir, "documents", "doc_id", "text", "source"))
    return mixed.select("doc_id", "size", "source_size", "target", "taken", "copies")
