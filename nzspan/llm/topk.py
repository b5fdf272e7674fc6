"""Exact top-k inner products by the threshold algorithm.

Rows and queries are dealt into blocks of bounded size; each pair of a row block and a query block is one task. The task keeps
for every dimension the rows sorted by their value. A query walks down all lists at once, from the
end its own component favours, scores every row that it meets, and stops when the best score that an unseen row could still
have, the query applied to the values at the current depth, is below the k-th best so far. The
best of each block meet in one aggregate for each query.
"""

from __future__ import annotations

import numpy as np
import pandas as pd
from pyspark.sql import DataFrame, SparkSession, Window
from pyspark.sql import functions as F

from nzspan.session import ship, written

from . import common

#: Rows and queries of a block, and how far a walk goes at first.
ROWS, QUERIES, STEP = 4096, 512, 16


def threshold_top(vectors: np.ndarray, ids: np.ndarray, query: np.ndarray, own: int, k: int, lists: np.ndarray | None = None, step: int = STEP) -> tuple[list[tuple[int, int]], int]:
    """((score, id) of the k best rows but those with the query's own id, ties to smaller ids; rows scored).

    lists: for every dimension the row numbers by ascending value. Integers only, so scores are exact.
    """
    n, dims = vectors.shape
    if lists is None:
        lists = np.argsort(vectors, axis=0, kind="stable").T
    seen = ids == own
    best_scores, best_ids = np.zeros(0, np.int64), np.zeros(0, np.int64)
    used = np.flatnonzero(query)
    rising = query[used] > 0
    scored = depth = 0
    while depth < n:
        to = min(n, depth + step)
        # the favoured end of each list: the last rows where the component is positive, else the first
        met = np.concatenate([lists[used[~rising], depth:to].ravel(), lists[used[rising], n - to : n - depth].ravel()]) if len(used) else np.arange(n)
        fresh = np.unique(met[~seen[met]])
        if len(fresh):
            seen[fresh] = True
            scored += len(fresh)
            best_scores = np.concatenate([best_scores, vectors[fresh] @ query])
            best_ids = np.concatenate([best_ids, ids[fresh]])
            order = np.lexsort((best_ids, -best_scores))[:k]
            best_scores, best_ids = best_scores[order], best_ids[order]
        if not len(used):
            break
        edge = np.where(rising, lists[used, n - to], lists[used, to - 1])
        bound = int(query[used] @ vectors[edge, used])
        if len(best_scores) == k and best_scores[-1] > bound:  # on equality an unseen row might tie with a smaller id
            break
        depth, step = to, step * 2
    return list(zip(best_scores.tolist(), best_ids.tolist(), strict=True)), scored


def top_inner_products(vectors: DataFrame, queries: DataFrame, k: int = 10, rows: int = ROWS, per_block: int = QUERIES) -> DataFrame:
    """(query_id, rank, vec_id, score): for each query the k best of vectors, both (vec_id long, v array<long>).

    Candidates that share the query's id are left out; a query id that is repeated counts once, with its smallest vector. Vectors
    of other lengths than the query's, and rows without an id, take no part. Repeated rows are candidates as often. Empty inputs give no rows.
    """
    spark = vectors.sparkSession
    ship(spark)
    vectors = written(vectors.where("vec_id IS NOT NULL").select("vec_id", "v"), "topk-rows")
    queries = written(queries.where("vec_id IS NOT NULL").groupBy("vec_id").agg(F.min("v").alias("v")), "topk-queries")
    n_rows, n_queries = max(1, -(-vectors.count() // rows)), max(1, -(-queries.count() // per_block))
    block = lambda n: F.pmod(F.xxhash64("vec_id", "v"), F.lit(n)).cast("int")
    every = lambda n: F.explode(F.sequence(F.lit(0), F.lit(n - 1)))
    left = vectors.select("vec_id", "v", block(n_rows).alias("rb"), every(n_queries).alias("qb"))
    right = queries.select("vec_id", "v", block(n_queries).alias("qb"), every(n_rows).alias("rb"))

    def search(rows: pd.DataFrame, asked: pd.DataFrame) -> pd.DataFrame:
        out = []
        for width, group in asked.groupby(asked["v"].map(len)):
            fit = rows[rows["v"].map(len) == width] if len(rows) else rows
            if not len(fit) or not width:
                continue
            matrix, ids = np.stack(fit["v"].to_list()).astype(np.int64), fit["vec_id"].to_numpy(np.int64)
            lists = np.argsort(matrix, axis=0, kind="stable").T
            for own, query in zip(group["vec_id"], group["v"], strict=True):
                found, _ = threshold_top(matrix, ids, np.asarray(query, np.int64), own, k, lists)
                out += [(own, i, s) for s, i in found]
        return pd.DataFrame(out, columns=["query_id", "vec_id", "score"])

    found = left.groupBy("rb", "qb").cogroup(right.groupBy("rb", "qb")).applyInPandas(search, "query_id long, vec_id long, score long")
    rank = F.row_number().over(Window.partitionBy("query_id").orderBy(F.col("score").desc(), "vec_id"))
    return found.withColumn("rank", rank).where(F.col("rank") <= k).select("query_id", "rank", "vec_id", "score")


def integer_vectors(embeddings: DataFrame, scale: int = 1024) -> DataFrame:
    """(vec_id, v array<long>) with v = floor(scale * x) for x as double; rows with a null vector, or null or non-finite components, are left out."""
    whole = F.col("embedding").isNotNull() & F.forall("embedding", lambda x: x.isNotNull() & ~F.isnan(x) & (F.abs(x.cast("double")) < float("inf")))
    return embeddings.where(whole).select("vec_id", F.transform("embedding", lambda x: F.floor(F.lit(float(scale)) * x.cast("double"))).alias("v"))


def op8_topk(spark: SparkSession, sf_dir: str) -> DataFrame:
    """query_id, rank, vec_id, score: the ten best of all other embeddings for each whose vec_id is divisible by 100.

    Rows without an id, and vectors that are null or hold a null or no finite number, take no part. Repeated rows are candidates as often; ties
    go to the smaller id. An empty table gives no rows. Other columns are left aside.
    """
    vectors = integer_vectors(common.table(spark, sf_dir, "embeddings", "vec_id", "embedding"))
    return top_inner_products(vectors, vectors.where(F.col("vec_id") % 100 == 0))


OP8_SQL = """
WITH whole AS (
  SELECT vec_id, list_transform(embedding, lambda x: CAST(floor(1024 * CAST(x AS DOUBLE)) AS BIGINT)) AS v
  FROM embeddings
  WHERE embedding IS NOT NULL AND len(list_filter(embedding, lambda x: x IS NULL OR NOT isfinite(x))) = 0),
scored AS (
  SELECT q.vec_id AS query_id, c.vec_id AS vec_id,
         CAST(list_sum(list_transform(list_zip(q.v, c.v), lambda p: p[1] * p[2])) AS BIGINT) AS score
  FROM whole q JOIN whole c ON q.vec_id <> c.vec_id
  WHERE q.vec_id % 100 = 0),
ranked AS (
  SELECT query_id, CAST(row_number() OVER (PARTITION BY query_id ORDER BY score DESC, vec_id) AS INTEGER) AS rank, vec_id, score FROM scored)
SELECT query_id, rank, vec_id, score FROM ranked WHERE rank <= 10
"""
