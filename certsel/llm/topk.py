"""Exact top-k inner products by norm buckets, and the shared handling of vectors and query blocks.

Candidates are written once in the order of their lengths; a bucket is BUCKET_ROWS rows of nearly equal length.  A query enters a bucket with the score it
has to reach: the k-th best among the longest vectors, then the k-th best so far.  If even the bucket's longest vector
cannot reach it, the bucket is skipped.  Otherwise that score over both lengths is the cosine a candidate needs: where
it is high, only vectors whose value in the query's largest coordinate can give this cosine are taken; where it is low,
only vectors long enough are.  What is left is verified by its products.
"""

from __future__ import annotations

import math

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame, Window
from pyspark.sql import functions as F

from .common import discard, staged, tidy

K = 5
SCALE = 256.0
#: Queries that are sent to all tasks at a time: a fixed bound of 4,096 vectors, whatever the table's size.
QUERY_BLOCK = 4096
SEED_ROWS = 2048
BUCKET_ROWS = 8192
#: From this local cosine on, coordinates prune better than lengths.
COORDINATE_FROM = 0.3


def usable(df: DataFrame, id_col: str = "vec_id", vec_col: str = "embedding", zero: bool = True) -> DataFrame:
    """(vec_id, v array<double>) without vectors that are null, empty or hold null or non-finite values (or are all zero)."""
    v = F.transform(F.col(vec_col).cast("array<double>"), lambda x: x)
    d = df.select(F.col(id_col).cast("long").alias("vec_id"), v.alias("v")).where("vec_id is not null and v is not null and size(v) > 0")
    d = d.where(F.forall("v", lambda x: x.isNotNull() & ~F.isnan(x) & (F.abs(x) != float("inf"))))
    return d if zero else d.where(F.exists("v", lambda x: x != 0))


def query_blocks(queries: DataFrame, block: int = QUERY_BLOCK):
    """Yield (ids, list of vectors) in blocks of about `block` rows of a written table: a stated query set, met by all rows block by block."""
    n = queries.count()
    parts = max(1, math.ceil(n / block))
    for b in range(parts):
        rows = queries.where(F.pmod(F.xxhash64("vec_id"), F.lit(parts)) == b).collect() if n else []
        if rows:
            rows.sort(key=lambda r: (r.vec_id, r.v))
            yield np.array([r.vec_id for r in rows], dtype=np.int64), [np.array(r.v) for r in rows]


def by_block(queries: DataFrame, block: int, search) -> DataFrame | None:
    """search(ids, vectors) of every block, one after another; None without queries.

    Each block's result is written before the next one is fetched, so the driver holds one block at a time and no plan grows
    with the number of queries.
    """
    queries, path = staged(queries, "queries")
    paths, schema, waiting = [], None, None
    for ids, vectors in query_blocks(queries, block):
        if waiting is not None:
            _, done = staged(waiting, "block")
            paths.append(done)
        waiting = search(ids, vectors)
        schema = waiting.schema
    discard(queries.sparkSession, path)
    if not paths:
        return waiting
    _, done = staged(waiting, "block")
    return queries.sparkSession.read.schema(schema).parquet(*paths, done)


def in_buckets(batches, rows: int):
    """Record batches of `rows` rows (the last of fewer), however the given ones are cut."""
    held, count = [], 0
    for b in batches:
        while b.num_rows:
            part = b.slice(0, rows - count)
            held.append(part)
            count += part.num_rows
            b = b.slice(part.num_rows)
            if count == rows:
                yield pa.Table.from_batches(held).combine_chunks().to_batches()[0]
                held, count = [], 0
    if count:
        yield pa.Table.from_batches(held).combine_chunks().to_batches()[0]


def matrix(column: pa.Array, dim: int) -> tuple[np.ndarray, np.ndarray]:
    """Rows of a list column that have `dim` values, and their numbers."""
    sizes = np.asarray(column.value_lengths())
    at = np.flatnonzero(sizes == dim)
    if len(at) == len(sizes):
        return np.asarray(column.flatten()).reshape(-1, dim), at
    return (np.asarray(column.take(pa.array(at)).flatten()).reshape(-1, dim) if len(at) else np.empty((0, dim))), at


def best_of(scores: np.ndarray, ids: np.ndarray, k: int) -> np.ndarray:
    """Positions of the k highest scores, ties to smaller ids."""
    if len(scores) > 4 * k:
        at = np.flatnonzero(scores >= np.partition(scores, len(scores) - k)[len(scores) - k])
    else:
        at = np.arange(len(scores))
    return at[np.lexsort((ids[at], -scores[at]))[:k]]


class Bucket:
    """Vectors of similar length, longest first, with their directions' coordinates sorted when first needed."""

    def __init__(self, ids: np.ndarray, v: np.ndarray):
        length = np.sqrt((v * v).sum(axis=1))
        order = np.argsort(-length, kind="stable")
        self.ids, self.v, self.length = ids[order], v[order], length[order]
        self.sorted: dict[int, tuple[np.ndarray, np.ndarray]] = {}

    def coordinate(self, f: int):
        if f not in self.sorted:
            c = self.v[:, f] / np.maximum(self.length, 1e-300)
            order = np.argsort(c, kind="stable")
            self.sorted[f] = order, c[order]
        return self.sorted[f]

    def candidates(self, q: np.ndarray, q_length: float, bar: float) -> np.ndarray | slice | None:
        """Rows whose product with q can reach bar; None for no row."""
        reach = q_length * self.length[0] * (1 + 1e-9)
        if bar <= 0 or q_length == 0:
            return slice(None) if bar <= 0 else None
        if reach < bar:
            return None
        cosine = bar / reach
        if cosine >= COORDINATE_FROM:
            f = int(np.abs(q).argmax())
            x = q[f] / q_length
            slack = math.sqrt(max(0.0, 1 - cosine * cosine)) * math.sqrt(max(0.0, 1 - x * x)) + 1e-9
            order, c = self.coordinate(f)
            low = -1.1 if x <= -cosine else x * cosine - slack
            high = 1.1 if x >= cosine else x * cosine + slack
            return order[np.searchsorted(c, low):np.searchsorted(c, high, "right")]
        return slice(0, int(np.searchsorted(-self.length, -bar / q_length * (1 - 1e-9), "right")))


def _block_top(candidates: DataFrame, ids: np.ndarray, vectors: list, seeds: dict, k: int) -> DataFrame:
    """(query_id, vec_id, score) of each partition's best, for one block of queries.  seeds: ids and vectors by dimension."""
    lengths = [float(np.sqrt(q @ q)) for q in vectors]
    bars = []
    for i, q in zip(ids, vectors):
        own = seeds.get(len(q))
        s = np.sort((own[1] @ q)[own[0] != i]) if own is not None else np.empty(0)
        bars.append(float(s[-k]) if len(s) >= k else -math.inf)

    def run(batches):
        top: list = [(np.empty(0, np.int64), np.empty(0)) for _ in vectors]
        bar = list(bars)
        for b in in_buckets(batches, BUCKET_ROWS):
            own = b.column(0).to_numpy()
            for dim in {len(q) for q in vectors}:
                v, at = matrix(b.column(1), dim)
                if not len(v):
                    continue
                bucket = Bucket(own[at], v)
                for n, q in enumerate(vectors):
                    if len(q) != dim:
                        continue
                    got = bucket.candidates(q, lengths[n], bar[n])
                    if got is None:
                        continue
                    s, i = bucket.v[got] @ q, bucket.ids[got]
                    keep = (s >= bar[n]) & (i != ids[n])
                    i, s = np.concatenate([top[n][0], i[keep]]), np.concatenate([top[n][1], s[keep]])
                    best = best_of(s, i, k)
                    top[n] = i[best], s[best]
                    if len(best) == k:
                        bar[n] = max(bar[n], float(s[best[-1]]))
        q = np.repeat(ids, [len(t[0]) for t in top])
        yield pa.RecordBatch.from_arrays([pa.array(q), pa.array(np.concatenate([t[0] for t in top])), pa.array(np.concatenate([t[1] for t in top]))],
                                         names=["query_id", "vec_id", "score"])

    return candidates.mapInArrow(tidy(run), "query_id long, vec_id long, score double")


def top_products(df: DataFrame, every: int = 50, k: int = K, id_col: str = "vec_id", vec_col: str = "embedding", scale: float = SCALE) -> DataFrame:
    """query_id, rank, vec_id, score: the k highest inner products of floor(scale * x) vectors for each query.

    Queries are the rows whose id is divisible by `every`; candidates are all rows with another id and as many
    components.  Ties go to the smaller id; repeated rows are candidates each, and queries once.  Null ids and vectors that
    are null, empty or hold null or non-finite values take no part.  Fewer candidates give fewer rows, none give none.
    """
    spark = df.sparkSession
    d = usable(df, id_col, vec_col).select("vec_id", F.transform("v", lambda x: F.floor(x * scale).cast("double")).alias("v"))
    d = d.withColumn("length", F.sqrt(F.aggregate("v", F.lit(0.0), lambda a, x: a + x * x)))
    longest = d.orderBy(F.desc("length"), "vec_id").limit(SEED_ROWS).select("vec_id", "v").collect()
    seed_ids, seed_v = [r.vec_id for r in longest], [np.array(r.v) for r in longest]
    by_dim = {n: (np.array([i for i, p in zip(seed_ids, seed_v) if len(p) == n]), np.array([p for p in seed_v if len(p) == n])) for n in {len(p) for p in seed_v}}
    parts = max(1, math.ceil(d.count() / BUCKET_ROWS))
    candidates, _ = staged(d.repartitionByRange(parts, F.desc("length"), F.col("vec_id")).sortWithinPartitions(F.desc("length"), "vec_id").select("vec_id", "v"), "by-length")
    found = by_block(d.where(F.col("vec_id") % every == 0).select("vec_id", "v").distinct(), QUERY_BLOCK,
                     lambda ids, vectors: _block_top(candidates, ids, vectors, by_dim, k))
    if found is None:
        return spark.createDataFrame([], "query_id long, rank int, vec_id long, score long")
    w = Window.partitionBy("query_id").orderBy(F.desc("score"), "vec_id")
    return found.withColumn("rank", F.row_number().over(w)).where(F.col("rank") <= k).select("query_id", "rank", "vec_id", F.col("score").cast("long").alias("score"))


SQL = """
WITH d AS (SELECT vec_id, list_transform(embedding, lambda x: floor(256 * x::DOUBLE)) AS v FROM embeddings
           WHERE embedding IS NOT NULL AND len(list_filter(embedding, lambda x: x IS NULL OR NOT isfinite(x))) = 0),
s AS (SELECT q.vec_id AS query_id, c.vec_id, CAST(list_inner_product(q.v, c.v) AS BIGINT) AS score
      FROM d q JOIN d c ON q.vec_id % 50 = 0 AND q.vec_id <> c.vec_id),
r AS (SELECT *, CAST(row_number() OVER (PARTITION BY query_id ORDER BY score DESC, vec_id) AS INTEGER) AS rank FROM s)
SELECT query_id, rank, vec_id, score FROM r WHERE rank <= 5
"""
