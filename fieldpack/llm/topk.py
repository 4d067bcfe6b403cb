"""Exact top-k by inner product: columnar branch and bound over blocks.

Vectors are packed into blocks in vertical layout, one row of components per dimension. A block of
queries meets a block of candidates dimension block by dimension block: partial scores grow, and a
candidate is dropped as soon as its partial score plus the most that the remaining components can
add (the product of both remaining norms) stays below the query's k-th best so far. Survivors are
compacted before the next dimensions are read. Each task carries its queries' best from block to
block; the tasks' few best rows are merged at the end.

Queries are a stated set (ids divisible by 100) that meets all rows in packed blocks. Query blocks
are put into groups of bounded bytes and candidate blocks into portions; a group and a portion meet
by an equi-join on both numbers, so nothing is broadcast that grows with the input, and a task holds
one group's queries at a time. Candidates whose norm cannot reach any query's k-th best are dropped
before the first product.

Cases: null vectors and vectors with null, NaN or infinite components take no part; shorter vectors
are as if filled up with zeros; ties go to the smaller id; repeated candidate rows each count;
repeated query rows of equal id and vector are one query; scores outside 64 bits are clipped.
"""

from __future__ import annotations

from collections.abc import Iterator

import numpy as np
import pandas as pd
from pyspark.sql import DataFrame, SparkSession, Window
from pyspark.sql import functions as F

from .common import bound_batches, read_table, small_batches, stage

BLOCK_ROWS, QUERY_ROWS, DIMS = 4096, 256, 16
#: Bytes of query blocks in a group, and candidate blocks in a portion.
GROUP_BYTES, PORTION_BLOCKS = 32 << 20, 16
EXACT = float(1 << 53)


def pack_blocks(rows: DataFrame, size: int) -> DataFrame:
    """(n, dims, ids, keys, values): values are `dims` x n doubles, dimension by dimension."""

    def run(batches: Iterator[pd.DataFrame]) -> Iterator[pd.DataFrame]:
        ids, keys, vectors = [], [], []

        def block() -> pd.DataFrame:
            dims = max(map(len, vectors))
            out = np.zeros((dims, len(ids)))
            for j, v in enumerate(vectors):
                out[: len(v), j] = v
            got = pd.DataFrame({"n": [len(ids)], "dims": [dims], "ids": [np.array(ids, dtype=np.int64).tobytes()], "keys": [np.array(keys, dtype=np.int64).tobytes()], "values": [out.tobytes()]})
            ids.clear(), keys.clear(), vectors.clear()
            return got

        for pdf in batches:
            for i, key, v in zip(pdf["id"], pdf["key"], pdf["vector"]):
                ids.append(i), keys.append(key), vectors.append(v)
                if len(ids) == size:
                    yield block()
        if ids:
            yield block()

    return rows.mapInPandas(run, "n int, dims int, ids binary, keys binary, values binary")


class Best:
    """The best k candidates so far of a block of queries."""

    def __init__(self, n: int, k: int):
        self.k = k
        self.scores: list[np.ndarray] = [np.empty(0) for _ in range(n)]
        self.ids: list[np.ndarray] = [np.empty(0, dtype=np.int64) for _ in range(n)]

    def floor(self, q: int) -> float:
        return self.scores[q][-1] if len(self.scores[q]) == self.k else -np.inf

    def add(self, q: int, scores: np.ndarray, ids: np.ndarray) -> None:
        s, i = np.concatenate([self.scores[q], scores]), np.concatenate([self.ids[q], ids])
        order = np.lexsort((i, -s))[: self.k]
        self.scores[q], self.ids[q] = s[order], i[order]


def scan_block(queries: np.ndarray, query_ids: np.ndarray, values: np.ndarray, ids: np.ndarray, best: Best, dims: int = DIMS) -> int:
    """Brings `best` up to date with a block; returns how many candidate components were read after the first dimensions.

    `queries` is (nq, d), `values` is (d, n)."""
    d = max(queries.shape[1], values.shape[0])
    queries = np.pad(queries, ((0, 0), (0, d - queries.shape[1])))
    values = np.pad(values, ((0, d - values.shape[0]), (0, 0)))
    if queries.size and values.size and np.abs(queries).max() * np.abs(values).max() * d >= EXACT:
        return _scan_large(queries, query_ids, values, ids, best)
    cuts = list(range(dims, d, dims))
    q_left = [np.sqrt((queries[:, c:] ** 2).sum(axis=1)) for c in cuts]
    c_left = [np.sqrt((values[c:] ** 2).sum(axis=0)) for c in cuts]
    floors = np.array([best.floor(q) for q in range(len(queries))])
    reach = np.sqrt((queries**2).sum(axis=1))[:, None] * np.sqrt((values**2).sum(axis=0)) * (1 + 1e-9) + 1e-3
    some = (reach >= floors[:, None]).any(axis=0)
    values, ids, c_left = values[:, some], ids[some], [c[some] for c in c_left]
    first = queries[:, :dims] @ values[:dims]
    read = 0
    for q in range(len(queries)):
        at = np.flatnonzero(ids != query_ids[q])
        part = first[q, at]
        for step, c in enumerate(cuts):
            live = part + q_left[step][q] * c_left[step][at] * (1 + 1e-9) + 1e-3 >= best.floor(q)
            at, part = at[live], part[live]
            if not len(at):
                break
            upto = min(c + dims, d)
            read += (upto - c) * len(at)
            part = part + queries[q, c:upto] @ values[c:upto, at]
        if len(at):
            good = part >= best.floor(q)
            part, at = part[good], at[good]
            if len(at) > 4 * best.k:  # all ties of the k-th best stay
                least = -np.partition(-part, best.k - 1)[best.k - 1]
                part, at = part[part >= least], at[part >= least]
            best.add(q, part, ids[at])
    return read


def _scan_large(queries: np.ndarray, query_ids: np.ndarray, values: np.ndarray, ids: np.ndarray, best: Best) -> int:
    """Components too large for exact doubles: whole numbers of any length, then clipped to 64 bits."""
    whole = np.vectorize(int, otypes=[object])
    v = whole(values)
    top, low = (1 << 63) - 1, -(1 << 63)
    for q in range(len(queries)):
        at = np.flatnonzero(ids != query_ids[q])
        scores = [min(top, max(low, s)) for s in (whole(queries[q]) @ v[:, at])]
        all_scores = best.scores[q].tolist() + scores
        all_ids = best.ids[q].tolist() + ids[at].tolist()
        order = sorted(range(len(all_ids)), key=lambda j: (-all_scores[j], all_ids[j]))[: best.k]
        best.scores[q], best.ids[q] = np.array([all_scores[j] for j in order], dtype=object), np.array([all_ids[j] for j in order], dtype=np.int64)
    return values.size * len(queries)


def top_k(vectors: DataFrame, is_query, k: int = 10) -> DataFrame:
    """(query_id, rank, vec_id, score) for `vectors` (vec_id, embedding): the k best by the integer inner product of floor(1024 * x)."""
    spark = vectors.sparkSession
    clean = F.col("vec_id").isNotNull() & F.col("embedding").isNotNull() & ~F.exists("embedding", lambda x: x.isNull() | F.isnan(x) | (F.abs(x) == float("inf")))
    # floor() of a double is a long in Spark: beyond that range the double is already whole
    v = F.transform("embedding", lambda x: F.when(F.abs(x) < 2.0**40, F.floor(x.cast("double") * 1024).cast("double")).otherwise(x.cast("double") * 1024))
    rows = vectors.where(clean).select(F.col("vec_id").cast("long").alias("id"), F.xxhash64("embedding").alias("key"), v.alias("vector"))
    bound_batches(spark)
    candidates = stage(pack_blocks(rows, BLOCK_ROWS), "topk-candidates")
    queries = stage(pack_blocks(rows.where(is_query(F.col("id"))).dropDuplicates(["id", "key"]), QUERY_ROWS), "topk-queries")
    size = queries.agg(F.sum(F.octet_length("values").cast("long"))).first()[0] or 0
    groups, portions = max(1, -(-size // GROUP_BYTES)), max(1, -(-candidates.count() // PORTION_BLOCKS))
    number = lambda n: F.sequence(F.lit(0), F.lit(n - 1))
    q = queries.select(F.pmod(F.xxhash64("ids", "keys"), F.lit(groups)).cast("int").alias("grp"), F.explode(number(portions)).alias("portion"), *[F.col(c).alias(f"q_{c}") for c in queries.columns])
    c = candidates.withColumn("portion", F.pmod(F.xxhash64("ids"), F.lit(portions)).cast("int")).withColumn("grp", F.explode(number(groups)))

    def results(known: dict) -> Iterator[pd.DataFrame]:
        for _, q_ids, q_keys, best in known.values():
            for i in range(len(q_ids)):
                if len(best.ids[i]):
                    yield pd.DataFrame({"query_id": q_ids[i], "query_key": q_keys[i], "vec_id": best.ids[i], "score": [int(x) for x in best.scores[i]]})

    def run(batches: Iterator[pd.DataFrame]) -> Iterator[pd.DataFrame]:
        known: dict[bytes, tuple[np.ndarray, np.ndarray, np.ndarray, Best]] = {}
        now = None
        for pdf in batches:
            for r in pdf.itertuples(index=False):
                if r.grp != now:
                    yield from results(known)
                    known, now = {}, r.grp
                name = r.q_ids + r.q_keys
                if name not in known:
                    mat = np.frombuffer(r.q_values).reshape(r.q_dims, r.q_n).T
                    known[name] = np.ascontiguousarray(mat), np.frombuffer(r.q_ids, dtype=np.int64), np.frombuffer(r.q_keys, dtype=np.int64), Best(r.q_n, k)
                mat, q_ids, _, best = known[name]
                scan_block(mat, q_ids, np.frombuffer(r.values).reshape(r.dims, r.n), np.frombuffer(r.ids, dtype=np.int64), best)
        yield from results(known)

    with small_batches(spark, 4):
        found = stage(c.join(q, ["grp", "portion"]).mapInPandas(run, "query_id long, query_key long, vec_id long, score long"), "topk-found")
    order = Window.partitionBy("query_id", "query_key").orderBy(F.desc("score"), "vec_id")
    return found.withColumn("rank", F.row_number().over(order)).where(F.col("rank") <= k).select("query_id", "rank", "vec_id", "score")


def op4_top_k(spark: SparkSession, sf_dir: str) -> DataFrame:
    return top_k(read_table(spark, sf_dir, "embeddings", "vec_id", "embedding"), lambda i: i % 100 == 0)


OP4_SQL = """
WITH v AS (
  SELECT vec_id, list_transform(embedding, lambda x: CAST(floor(1024 * CAST(x AS DOUBLE)) AS BIGINT)) AS e FROM embeddings
  WHERE embedding IS NOT NULL AND len(list_filter(embedding, lambda x: x IS NULL OR NOT isfinite(x))) = 0),
s AS (
  SELECT q.vec_id AS query_id, c.vec_id, CAST(list_sum(list_transform(list_zip(q.e, c.e), lambda p: p[1] * p[2])) AS BIGINT) AS score
  FROM v q JOIN v c ON q.vec_id % 100 = 0 AND q.vec_id <> c.vec_id)
SELECT query_id, CAST(rank AS INTEGER) AS rank, vec_id, score
FROM (SELECT *, row_number() OVER (PARTITION BY query_id ORDER BY score DESC, vec_id) AS rank FROM s) WHERE rank <= 10
"""
