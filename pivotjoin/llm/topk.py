"""Operator 9: exact top-k by inner product, term at a time."""

from __future__ import annotations

from collections.abc import Iterator

import numpy as np
import pyarrow as pa
from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F
from pyspark.sql.window import Window

K, EVERY, SCALE = 5, 50, 256
#: Rows of a block of queries and of one of candidates; one task holds one of each.
QUERY_ROWS, CANDIDATE_ROWS, MOST_CANDIDATE_ROWS = 4096, 1024, 32_768
#: Queries whose dense score rows are held at once, and scores that are added to at once.
SCORED_ROWS, SCORED_AT_ONCE = 128, 1 << 17
#: Blocks of candidates whose best rows meet before those of all blocks do.
MERGED_BLOCKS = 64
FOUND = "query_id long, vec_id long, score long, part long"


def usable(v: Column) -> Column:
    """Whether a vector takes part: not null, no null or non-finite component."""
    return v.isNotNull() & F.forall(v, lambda x: x.isNotNull() & ~F.isnan(x) & (F.abs(x) < float("inf")))


def matrix(lists: pa.Array) -> np.ndarray:
    """Rows of longs; shorter rows are filled up with zeros."""
    flat, ends = lists.flatten().to_numpy(zero_copy_only=False).astype(np.int64), np.concatenate(([0], np.cumsum([0 if n is None else n for n in lists.value_lengths().to_pylist()])))
    widths = np.diff(ends)
    out = np.zeros((len(widths), int(widths.max(initial=0))), np.int64)
    rows = np.repeat(np.arange(len(widths)), widths)
    out[rows, np.arange(len(flat)) - ends[rows]] = flat
    return out


def best(q_ids: np.ndarray, q: np.ndarray, ids: np.ndarray, c: np.ndarray, k: int = K) -> tuple[np.ndarray, np.ndarray, np.ndarray]:
    """(query id, candidate id, score) of each query's k best candidates of other ids, ties to the smaller id.

    For every term the queries that have it add their weight times the term's postings to dense
    rows of scores, few rows at a time, so that they stay in the cache; then each row is partitioned at its k-th place.
    """
    order = np.argsort(ids, kind="stable")
    ids, c = ids[order], c[order]
    width = min(q.shape[1], c.shape[1])
    peak = int(np.abs(q).max(initial=0)) * int(np.abs(c).max(initial=0)) * max(width, 1)
    kind = np.int64 if (peak + 1) * (len(ids) + 1) < 2**62 else object  # beyond, Python's integers
    small = np.int32 if peak < 2**31 else kind
    postings = []
    for t in range(width):
        at = np.flatnonzero(c[:, t])
        # a term that most candidates have is added to whole rows
        postings.append((None, c[:, t].astype(small)) if 2 * len(at) > len(ids) else (at, c[at, t].astype(small)))
    step = max(1, SCORED_AT_ONCE // max(1, len(ids)))
    out_q, out_c, out_s = [], [], []
    for a in range(0, len(q_ids), SCORED_ROWS):
        part, own = q[a : a + SCORED_ROWS].astype(kind), q_ids[a : a + SCORED_ROWS]
        scores = np.zeros((len(own), len(ids)), small)
        for r in range(0, len(own), step):
            rows, weigh = scores[r : r + step], part[r : r + step].astype(small)
            for t, (at, weights) in enumerate(postings):
                if at is None:
                    rows += weigh[:, t, None] * weights
                else:
                    for i in np.flatnonzero(weigh[:, t]):
                        rows[i, at] += weigh[i, t] * weights
        scores = scores.astype(kind)
        key = scores * len(ids) - np.arange(len(ids))
        low = -(peak + 1) * (len(ids) + 1)
        same = own[:, None] == ids[None, :]
        key[same] = low
        n = min(k, len(ids))
        top = np.argpartition(-key, n - 1, axis=1)[:, :n] if kind is np.int64 else np.argsort(-key, axis=1)[:, :n]
        row = np.repeat(np.arange(len(own)), n)
        top = top.ravel()
        keep = ~same[row, top]
        row, top = row[keep], top[keep]
        out_q.append(own[row])
        out_c.append(ids[top])
        out_s.append(np.clip(scores[row, top], -(2**63), 2**63 - 1).astype(np.int64))
    return np.concatenate(out_q), np.concatenate(out_c), np.concatenate(out_s)


def top_k(vectors: DataFrame, k: int = K, every: int = EVERY, id_col: str = "vec_id", vec_col: str = "embedding") -> DataFrame:
    """(query_id, rank, vec_id, score) of each query's k best other rows.

    Queries are the rows whose id is divisible by ``every``. Queries and candidates are dealt into
    blocks by a hash of the id; each pair of blocks goes to one task, which holds no more than one
    of each and returns k rows per query; these are merged by groups of blocks first. Rows of a null id take no part; of repeated rows each is
    a candidate, and none is one for a query of the same id; a repeated query is one query, with the least of its vectors; vectors
    of unlike lengths are filled up with zeros; an empty table gives no rows.
    """
    whole = F.transform(vectors[vec_col], lambda x: F.floor(x.cast("double") * SCALE))
    x = vectors.where(usable(vectors[vec_col]) & vectors[id_col].isNotNull()).select(vectors[id_col].cast("long").alias("vec_id"), whole.alias("v"))
    n = vectors.count()
    rows = min(max(CANDIDATE_ROWS, n // (8 * int(vectors.sparkSession.conf.get("spark.sql.shuffle.partitions")))), MOST_CANDIDATE_ROWS)
    c_blocks, q_blocks = -(-n // rows) or 1, -(-n // (every * QUERY_ROWS)) or 1
    block = lambda of, salt: F.pmod(F.xxhash64("vec_id", F.lit(salt)), F.lit(of)).cast("int")
    queries = x.where(F.col("vec_id") % every == 0).groupBy("vec_id").agg(F.min("v").alias("v"))
    queries = queries.select(F.col("vec_id").alias("query_id"), "v", block(q_blocks, 1).alias("qb"), F.explode(F.sequence(F.lit(0), F.lit(c_blocks - 1))).alias("cb"))
    candidates = x.select("vec_id", "v", block(c_blocks, 2).alias("cb"), F.explode(F.sequence(F.lit(0), F.lit(q_blocks - 1))).alias("qb"))

    def run(q: pa.Table, c: pa.Table) -> pa.Table:
        if not (q.num_rows and c.num_rows):
            found = [np.empty(0, np.int64)] * 3
        else:
            ids = [q.column("query_id").to_numpy(), c.column("vec_id").to_numpy()]
            vs = [matrix(t.column("v").combine_chunks()) for t in (q, c)]
            found = best(ids[0], vs[0], ids[1], vs[1], k)
        part = c.column("cb")[0].as_py() // MERGED_BLOCKS if c.num_rows else 0
        return pa.table({name: pa.array(v, pa.int64()) for name, v in zip(("query_id", "vec_id", "score", "part"), (*found, np.full(len(found[0]), part)), strict=True)})

    found = queries.groupBy("qb", "cb").cogroup(candidates.groupBy("qb", "cb")).applyInArrow(run, FOUND)
    place = lambda *keys: F.row_number().over(Window.partitionBy("query_id", *keys).orderBy(F.desc("score"), "vec_id"))
    if c_blocks > MERGED_BLOCKS:
        found = found.withColumn("rank", place("part")).where(F.col("rank") <= k)
    return found.withColumn("rank", place()).where(F.col("rank") <= k).select("query_id", "rank", "vec_id", "score")


def op9(vectors: DataFrame) -> DataFrame:
    return top_k(vectors)


ORACLE = """
WITH x AS (SELECT vec_id, list_transform(embedding, lambda e: floor(256 * CAST(e AS DOUBLE))) AS v FROM embeddings
           WHERE embedding IS NOT NULL AND len(list_filter(embedding, lambda e: e IS NULL OR NOT isfinite(e))) = 0),
s AS (SELECT q.vec_id AS query_id, c.vec_id AS vec_id, CAST(list_inner_product(q.v, c.v) AS BIGINT) AS score
      FROM x q JOIN x c ON q.vec_id % 50 = 0 AND c.vec_id <> q.vec_id)
SELECT query_id, CAST(rank AS INT) AS rank, vec_id, score
FROM (SELECT *, row_number() OVER (PARTITION BY query_id ORDER BY score DESC, vec_id) AS rank FROM s) WHERE rank <= 5
"""
