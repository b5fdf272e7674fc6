"""SimHash near-duplicates through a popcount embedding.

A fingerprint has 64 bits: bit b is set if over half of the text's shingle hashes have it set. Two
texts are linked when their fingerprints differ in few bits. For the search a fingerprint is embedded as
the vector of its popcounts over segments of two bits. The Manhattan distance of two such vectors never
exceeds the Hamming distance of the fingerprints, so what is further apart in the grid cannot be linked.

The range join runs on a grid over that space: the segments form eight groups of four; points within
Manhattan distance 4 agree on the popcounts of at least four whole groups, so every linked pair meets in
one of the 70 cells made from four groups each. Within a cell the Manhattan distance prunes, and the
Hamming distance decides. A cell keeps a spanning forest of its links and not all pairs; cells of
many fingerprints are cut into blocks, every pair of blocks being a task of bounded size.
"""

from __future__ import annotations

from itertools import combinations

import numpy as np
import pandas as pd
import pyarrow as pa
import xxhash
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from nzspan.session import ship, written

from . import common
from .components import connected_components

BITS, RADIUS, GROUPS, SHINGLE, SEED = 64, 4, 8, 4, 42
#: Fingerprints that one side of a block comparison holds.
BLOCK = 2048


def fingerprint(text: str | None, shingle: int = SHINGLE, seed: int = SEED) -> int:
    """The 64-bit SimHash of a text; 0 for a text without words. Words are joined by single spaces; fewer words than a shingle make one."""
    words = common.byte_words(text)
    if not words:
        return 0
    data = b" ".join(words)
    width = min(shingle, len(words))
    lengths = np.fromiter(map(len, words), np.int64, len(words))
    ends = np.cumsum(lengths + 1) - 1
    starts = (ends - lengths)[: len(words) - width + 1].tolist()
    digest = xxhash.xxh64_intdigest
    return majority([digest(data[a:b], seed) for a, b in zip(starts, ends[width - 1 :].tolist(), strict=True)])


def majority(hashes: list[int]) -> int:
    """Bits set in over half of the hashes."""
    counts, at = np.zeros(BITS, np.int64), np.array(hashes, np.uint64)
    for lo in range(0, len(at), 1 << 16):
        counts += np.unpackbits(at[lo : lo + (1 << 16)].astype(">u8").view(np.uint8).reshape(-1, 8), axis=1).sum(axis=0, dtype=np.int64)
    return int.from_bytes(np.packbits(counts * 2 > len(at)).tobytes(), "big")


def fingerprints(documents: DataFrame, shingle: int = SHINGLE, seed: int = SEED) -> DataFrame:
    """(doc_id, fp long) of documents(doc_id, text)."""
    ship(documents.sparkSession)

    def make():
        def step(columns: dict) -> dict:
            found = [fingerprint(t.as_py(), shingle, seed) for t in columns["text"]]
            return {"doc_id": columns["doc_id"], "fp": pa.array(np.array(found, np.uint64).view(np.int64))}

        return step

    return common.arrow_map(documents.select("doc_id", "text"), make, "doc_id long, fp long")


def cell_masks() -> list[int]:
    """The 70 ways to choose four groups of the eight, as signed 64-bit masks."""
    width = BITS // GROUPS
    group = [((1 << width) - 1) << (width * g) for g in range(GROUPS)]
    masks = [sum(chosen) for chosen in combinations(group, GROUPS // 2)]
    return [m - (1 << BITS) if m >> (BITS - 1) else m for m in masks]


def in_cells(prints: DataFrame) -> DataFrame:
    """(node, fp, cell): a row for each of the cells of a fingerprint. A cell's key is a hash, so cells may merge, which costs a comparison and no link."""
    fp = F.col("fp")
    low, high = fp.bitwiseAND(F.lit(0x5555555555555555)), F.shiftrightunsigned(fp, 1).bitwiseAND(F.lit(0x5555555555555555))
    # popcounts of all 32 segments at once: each field of two bits holds 0, 1 or 2
    counts = F.shiftleft(low.bitwiseAND(high), 1).bitwiseOR(low.bitwiseXOR(high))
    spread = prints.select("node", "fp", counts.alias("counts"), F.explode(F.array(*map(F.lit, cell_masks()))).alias("mask"))
    return spread.select("node", "fp", F.xxhash64("mask", F.col("counts").bitwiseAND(F.col("mask"))).alias("cell"))


def hamming(a: np.ndarray, b: np.ndarray) -> np.ndarray:
    return np.bitwise_count(a ^ b)


def segment_distance(a: np.ndarray, b: np.ndarray) -> np.ndarray:
    """Manhattan distance of the popcount vectors: a bound below the Hamming distance, from four masked counts."""
    low = np.uint64(0x5555555555555555)
    one = np.uint64(1)
    high_a, high_b, low_a, low_b = (a >> one) & low, (b >> one) & low, a & low, b & low
    both_a, any_a, both_b, any_b = high_a & low_a, high_a | low_a, high_b & low_b, high_b | low_b
    return np.bitwise_count(both_a ^ both_b) + np.bitwise_count(any_a ^ any_b)


class Forest:
    """Union-find over positions 0..n-1."""

    def __init__(self, n: int):
        self.up = list(range(n))

    def root(self, i: int) -> int:
        while self.up[i] != i:
            self.up[i] = self.up[self.up[i]]
            i = self.up[i]
        return i

    def join(self, i: int, j: int) -> bool:
        i, j = self.root(i), self.root(j)
        if i != j:
            self.up[max(i, j)] = min(i, j)
        return i != j


def forest_links(left: np.ndarray, right: np.ndarray | None, radius: int) -> list[tuple[int, int]]:
    """A spanning forest of the links within left, or from left to right; positions, those of right after left's."""
    points = left if right is None else np.concatenate([left, right])
    forest, out = Forest(len(points)), []
    for i in range(len(left) if right is not None else len(left) - 1):
        lo = i + 1 if right is None else len(left)
        rest = points[lo:]
        near = np.flatnonzero(segment_distance(points[i], rest) <= radius)
        near = near[hamming(points[i], rest[near]) <= radius] + lo
        out += [(i, int(j)) for j in near if forest.join(i, int(j))]
    return out


def fingerprint_links(prints: DataFrame, radius: int = RADIUS, block: int = BLOCK) -> DataFrame:
    """(a, b): edges between nodes of prints(node, fp), one node for each fingerprint, with the same components as all links have."""
    if radius >= GROUPS - GROUPS // 2 + 1:
        raise ValueError("the grid has all links up to a radius of 4 only")
    spark = prints.sparkSession
    ship(spark)
    celled = in_cells(prints)
    crowded = celled.groupBy("cell").agg(F.count(F.lit(1)).alias("n")).where("n > 1")
    # Spark takes the 70 rows of a fingerprint for one, and would send them all through the driver
    met = celled.join(crowded.hint("merge"), "cell")
    # a cell of up to `block` fingerprints is compared as a whole; a larger one as pairs of blocks, in each of which a fingerprint stands once
    blocks = F.ceil(F.col("n") / block).cast("int")
    own = F.pmod(F.xxhash64("fp", F.lit(SEED)), blocks).cast("int")
    other = F.explode(F.sequence(F.lit(0), blocks - 1))
    met = met.select("cell", "node", "fp", own.alias("own"), other.alias("other"))
    met = met.select("cell", "node", "fp", F.least("own", "other").alias("one"), F.greatest("own", "other").alias("two"), "own")
    met = met.repartition("cell", "one", "two").sortWithinPartitions("cell", "one", "two", "own", "fp")

    def run(batches):
        held: list[pd.DataFrame] = []
        for batch in batches:
            rows = batch.to_pandas()
            if held:
                rows = pd.concat([*held, rows], ignore_index=True)
            key = rows[["cell", "one", "two"]].to_numpy()
            cuts = np.flatnonzero((key[1:] != key[:-1]).any(axis=1)) + 1
            last = int(cuts[-1]) if len(cuts) else 0
            if last:
                yield _links_of(rows.iloc[:last], np.concatenate([[0], cuts]), radius)
            held = [rows.iloc[last:]]
        if held and len(held[0]):
            yield _links_of(held[0], np.array([0, len(held[0])]), radius)

    return met.mapInArrow(common.frugal(run), "a long, b long").distinct()


def _links_of(rows: pd.DataFrame, cuts: np.ndarray, radius: int) -> pa.RecordBatch:
    node, fp = rows["node"].to_numpy(), rows["fp"].to_numpy().view(np.uint64)
    own, two, one = rows["own"].to_numpy(), rows["two"].to_numpy(), rows["one"].to_numpy()
    found_a, found_b = [], []
    size = np.diff(cuts)
    pair = cuts[:-1][size == 2]  # most cells: all pairs at once
    near = pair[hamming(fp[pair], fp[pair + 1]) <= radius]
    found_a.append(node[near])
    found_b.append(node[near + 1])
    for lo, hi in zip(cuts[:-1][size > 2], cuts[1:][size > 2], strict=True):
        cut = lo + int(np.searchsorted(own[lo:hi], two[lo])) if one[lo] != two[lo] else hi
        links = forest_links(fp[lo:cut], None if cut == hi and one[lo] == two[lo] else fp[cut:hi], radius)
        if links:
            i, j = np.array(links).T
            found_a.append(node[lo:hi][i])
            found_b.append(node[lo:hi][j])
    a, b = np.concatenate(found_a), np.concatenate(found_b)
    return pa.RecordBatch.from_arrays([pa.array(a, pa.int64()), pa.array(b, pa.int64())], names=["a", "b"])


def near_duplicates(documents: DataFrame, shingle: int = SHINGLE, radius: int = RADIUS, seed: int = SEED, block: int = BLOCK) -> DataFrame:
    """(doc_id, fp, component_id) for every row of documents(doc_id, text); component_id is the smallest doc_id that links reach.

    Null and empty texts have fingerprint 0 and are linked like others. Equal fingerprints are one node, so groups of copies
    are never expanded. Repeated doc_ids keep their rows; null doc_ids form no node of their own but for their fingerprint.
    An empty table gives no rows. Other columns of documents are left aside.
    """
    prints = written(fingerprints(documents, shingle, seed), "simhash")
    nodes = written(prints.groupBy("fp").agg(F.min("doc_id").alias("node")).where("node IS NOT NULL"), "simhash-nodes")
    labels = connected_components(fingerprint_links(nodes, radius, block))
    named = nodes.join(labels, "node", "left").select("fp", F.coalesce("component", "node").alias("component_id"))
    return prints.join(named, "fp", "left").select("doc_id", "fp", "component_id")


def op5_simhash(spark: SparkSession, sf_dir: str) -> DataFrame:
    """doc_id, fingerprint, component_id of all documents.

    Null and empty texts have fingerprint zero, and are linked by it. Repeated rows keep their place; rows without a doc_id have the
    component of their fingerprint. An empty table gives no rows. Other columns are left aside.
    """
    found = near_duplicates(common.table(spark, sf_dir, "documents", "doc_id", "text"))
    return found.select("doc_id", F.lower(F.lpad(F.hex("fp"), 16, "0")).alias("fingerprint"), "component_id")
