"""Exact top-k search by exhaustive term-at-a-time accumulation.

A vector is a sparse row of (term, weight): the term is the component's index, the weight an integer that is not 0.
Candidates are cut into blocks, and each block is turned into one postings list per term: the candidates that have it,
and their weights.  A strip of query rows walks the terms one after another; for each, its postings, times the queries'
weights, are scattered into a dense score array with a row per candidate and a column per query.  A partition selection
keeps each query's k best of the block; the short lists of all blocks are then merged.

Plan: queries are `query_block`-sized groups, candidates `candidate_block`-sized groups (both by a hash of vec_id,
with the number of groups taken from a count), and each pair of groups is one task's input, so no side is broadcast and
a task's memory depends on the block sizes alone.  The search is exhaustive, so for n candidates and m queries
n * m / query_block and n * m / candidate_block rows travel.  What leaves a pair is k rows per query; the merge ranks
k * candidate_groups rows per query.
"""

from __future__ import annotations

import math

import numpy as np
import pandas as pd
from pyspark.sql import DataFrame, SparkSession, Window
from pyspark.sql import functions as F

from ..session import ship
from .common import table

CANDIDATE_BLOCK = 4096
QUERY_BLOCK = 1024
#: Queries scored at once inside a task: bounds the dense score array to STRIP * CANDIDATE_BLOCK cells.
STRIP = 64


def quantised(vectors: DataFrame, scale: int = 64, id_col: str = "vec_id", vec_col: str = "embedding") -> DataFrame:
    """(vec_id long, weights array<long>) with weight floor(scale * x), x as double.

    Vectors that are null or hold a null, NaN or infinite component, and rows without an id, take no part.  A row that
    repeats another's id and weights counts once; rows that share an id with other weights are candidates and queries of
    their own.  A component whose weight is beyond 2**62 is an error, as scores would be beyond a long.  Other columns are
    dropped; an empty table gives none.
    """
    wide = F.lit(float(1 << 62))
    weight = lambda v: F.when(F.abs(v) < wide, F.floor(v)).otherwise(F.raise_error(F.lit("a component is too large for integer scores")).cast("long"))
    x = F.col(vec_col)
    fine = x.isNotNull() & F.col(id_col).isNotNull() & F.forall(
        x, lambda v: v.isNotNull() & ~F.isnan(v.cast("double")) & (F.abs(v.cast("double")) < F.lit(float("inf")))
    )
    return (
        vectors.filter(fine)
        .select(F.col(id_col).cast("long").alias("vec_id"), F.transform(x, lambda v: weight(v.cast("double") * F.lit(float(scale)))).alias("weights"))
        .dropDuplicates(["vec_id", "weights"])
    )


def _exact_kind(reach: int) -> type:
    """The fastest number type in which no sum of magnitude up to reach is rounded or wraps; Python's own beyond 64 bits."""
    return np.float32 if reach < 2**24 else np.float64 if reach < 2**53 else np.int64 if reach < 2**63 else object


class Postings:
    """Postings lists of one candidate block: per term the candidates with a weight, and the weights."""

    def __init__(self, rows: np.ndarray, kind: type) -> None:
        self.width, self.kind = len(rows), kind
        self.lists = []
        for t in range(rows.shape[1]):
            at = np.flatnonzero(rows[:, t])
            if len(at):
                self.lists.append((t, at, rows[at, t].astype(kind)[:, None]))

    def scores(self, queries: np.ndarray) -> np.ndarray:
        """Dense score array (candidate x query): every term's weighted postings are added once."""
        score = np.zeros((self.width, len(queries)), self.kind)
        add, held = np.empty_like(score), np.empty_like(score)
        for t, at, weights in self.lists:
            having = np.flatnonzero(queries[:, t])
            if 4 * len(having) < len(queries):
                if len(having):
                    score[np.ix_(at, having)] += weights * queries[having, t].astype(self.kind)
                continue
            # Many queries have the term: whole rows of the score array are taken, added to (0 for the others) and put back.
            more, rows = add[: len(at)], held[: len(at)]
            np.multiply(weights, queries[:, t].astype(self.kind), out=more)
            np.take(score, at, axis=0, out=rows, mode="clip")
            rows += more
            score[at] = rows
        return score


def _matrix(rows: list, terms: int) -> np.ndarray:
    """Rows of weights side by side, zeros where a row has no such term."""
    out = np.zeros((len(rows), terms), np.int64)
    for i, w in enumerate(rows):
        out[i, : len(w)] = w[:terms]
    return out


def _best(score: np.ndarray, ids: np.ndarray, k: int) -> np.ndarray:
    """Places of the k best of one query, ids ascending: partition selection by score, ties at the border by smaller id."""
    if len(score) <= k:
        return np.arange(len(score))
    border = np.partition(score, len(score) - k)[len(score) - k]
    above = np.flatnonzero(score > border)
    return np.concatenate([above, np.flatnonzero(score == border)[: k - len(above)]])


def _best_of_pair(k: int):
    def run(left: pd.DataFrame, right: pd.DataFrame) -> pd.DataFrame:
        out: list[tuple] = []
        if len(left) and len(right):
            right = right.sort_values("vec_id", kind="stable")
            ids = right["vec_id"].to_numpy(np.int64)
            terms = max(map(len, right["weights"]))
            dense, sought = _matrix(right["weights"], terms), _matrix(left["weights"], terms)
            reach = max(map(abs, (int(sought.max(initial=0)), int(sought.min(initial=0))))) * max(map(abs, (int(dense.max(initial=0)), int(dense.min(initial=0))))) * max(terms, 1)
            postings = Postings(dense, _exact_kind(reach))
            own = left["vec_id"].to_numpy(np.int64)
            for at in range(0, len(own), STRIP):
                score = postings.scores(sought[at : at + STRIP])
                for q, vec_id in enumerate(own[at : at + STRIP].tolist()):
                    others = np.flatnonzero(ids != vec_id)
                    best = others[_best(score[others, q], ids[others], k)]
                    out += [(vec_id, int(ids[c]), int(score[c, q])) for c in best]
        if any(abs(x[2]) >= 2**63 for x in out):
            raise OverflowError("a score is beyond a long")
        return pd.DataFrame(out, columns=["query_id", "vec_id", "score"]).astype("int64")

    return run


def top_k(vectors: DataFrame, queries: DataFrame, k: int = 20, candidate_block: int = CANDIDATE_BLOCK, query_block: int = QUERY_BLOCK) -> DataFrame:
    """The k best candidates of every query row by integer inner product.

    vectors, queries: (vec_id long, weights array<long>), as quantised() makes them; rows of different length are
    compared over the terms both have.  A candidate with the query's own id is left out.  Ties go to the smaller
    vec_id.  Result: query_id, rank (from 1), vec_id, score; a query with fewer than k candidates has them all; empty
    inputs give no rows.
    """
    ship(vectors.sparkSession)
    n, m = vectors.count(), queries.count()
    groups, sets = max(1, math.ceil(n / candidate_block)), max(1, math.ceil(m / query_block))
    place = lambda parts: F.pmod(F.xxhash64("vec_id", "weights"), F.lit(parts)).cast("int")
    spread = lambda parts: F.explode(F.sequence(F.lit(0), F.lit(parts - 1)))
    left = queries.withColumn("qb", place(sets)).withColumn("cb", spread(groups))
    right = vectors.withColumn("cb", place(groups)).withColumn("qb", spread(sets))
    pairs = left.groupBy("qb", "cb").cogroup(right.groupBy("qb", "cb")).applyInPandas(_best_of_pair(k), "query_id long, vec_id long, score long")
    best = Window.partitionBy("query_id").orderBy(F.desc("score"), F.asc("vec_id"))
    return pairs.withColumn("rank", F.row_number().over(best)).filter(F.col("rank") <= k).select("query_id", "rank", "vec_id", "score")


def op1_exact_topk(spark: SparkSession, sf_dir: str) -> DataFrame:
    vectors = quantised(table(spark, sf_dir, "embeddings"))
    return top_k(vectors, vectors.filter(F.col("vec_id") % 20 == 0), 20)


OP1_SQL = """
WITH v AS (
  SELECT DISTINCT CAST(vec_id AS BIGINT) AS vec_id,
         list_transform(embedding, lambda x: CAST(floor(64 * CAST(x AS DOUBLE)) AS BIGINT)) AS w
  FROM embeddings
  WHERE vec_id IS NOT NULL AND embedding IS NOT NULL
    AND len(list_filter(embedding, lambda x: x IS NULL OR NOT isfinite(x))) = 0),
s AS (
  SELECT q.vec_id AS query_id, c.vec_id,
         CAST(coalesce(list_sum(list_transform(list_zip(q.w, c.w, true), lambda z: z[1] * z[2])), 0) AS BIGINT) AS score
  FROM v q JOIN v c ON q.vec_id % 20 = 0 AND q.vec_id <> c.vec_id),
r AS (SELECT query_id, row_number() OVER (PARTITION BY query_id ORDER BY score DESC, vec_id) AS rank, vec_id, score FROM s)
SELECT query_id, CAST(rank AS INTEGER) AS rank, vec_id, score FROM r WHERE rank <= 20
"""
