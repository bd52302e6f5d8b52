"""Approximate nearest neighbours: an inverted file of coarse centroids with product-quantised residuals.

The coarse centroids and the sub-space codebooks are fitted by k-means on a bounded sample (IndexSettings.sample_rows); every row is then
indexed: its list, its residual's codes and the vector itself.  A query probes the lists of its nearest centroids, ranks their
rows by asymmetric distance tables, and the best of them all are reranked by exact distance on the original vectors.
The k-th best of these is a radius that holds the true k nearest.  A second look at the index with it skips lists by their
farthest row and rows by the error of their codes (triangle inequality), and verifies the rest, so the answer is exact.
The index is written in the order of its lists, a large list over several tasks; a task looks at a list with the queries that probe it.
"""

from __future__ import annotations

import math
from dataclasses import dataclass, replace

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame, Window
from pyspark.sql import functions as F

from .common import discard, staged, tidy
from .topk import by_block, matrix, usable

K = 10
SCHEMA = "vec_id long, list int, codes binary, bias double, v array<double>"


@dataclass(frozen=True)
class IndexSettings:
    """lists: 0 for four times the square root of the rows, as far as the sample carries that many; probes: a share of the lists."""

    sample_rows: int = 16_384
    lists: int = 0
    sub_spaces: int = 16
    codes: int = 256
    probes: float = 0.25
    rows_per_task: int = 32_768
    query_block: int = 1024
    rerank: int = 128
    rounds: int = 8
    seed: int = 5


def _squared(a: np.ndarray, b: np.ndarray) -> np.ndarray:
    return np.maximum((a * a).sum(1)[:, None] + (b * b).sum(1)[None] - 2 * a @ b.T, 0)


def k_means(x: np.ndarray, k: int, rounds: int, rng) -> np.ndarray:
    """Centroids; an empty one moves to the point farthest from its own."""
    c = x[rng.choice(len(x), min(k, len(x)), replace=False)].copy()
    for _ in range(rounds):
        d = _squared(x, c)
        own = d.argmin(axis=1)
        n = np.bincount(own, minlength=len(c))
        total = np.zeros_like(c)
        np.add.at(total, own, x)
        far = np.argsort(-d[np.arange(len(x)), own])
        c = np.where(n[:, None] > 0, total / np.maximum(n, 1)[:, None], x[far[np.arange(len(c)) % len(x)]])
    return c


def fitted_to(s: IndexSettings, rows: int) -> IndexSettings:
    return replace(s, lists=s.lists or max(1, min(int(4 * math.sqrt(rows)), min(rows, s.sample_rows) // 32)))


class Quantizer:
    """Coarse centroids and one codebook per sub-space, all for vectors of one dimension."""

    def __init__(self, x: np.ndarray, s: IndexSettings):
        rng = np.random.default_rng(s.seed)
        self.dim = x.shape[1]
        self.coarse = k_means(x, s.lists, s.rounds, rng)
        left = x - self.coarse[_squared(x, self.coarse).argmin(axis=1)]
        self.parts = np.array_split(np.arange(self.dim), min(s.sub_spaces, self.dim))
        self.books = [k_means(left[:, p], s.codes, s.rounds, rng) for p in self.parts]

    def encode(self, x: np.ndarray) -> tuple[np.ndarray, np.ndarray]:
        own = _squared(x, self.coarse).argmin(axis=1)
        left = x - self.coarse[own]
        return own, np.stack([_squared(left[:, p], b).argmin(axis=1) for p, b in zip(self.parts, self.books)], axis=1).astype(np.uint8)

    def bias(self, own: np.ndarray, codes: np.ndarray) -> np.ndarray:
        """What a row adds to its squared distance from any query: |r|^2 + 2 c.r for its decoded residual r and centroid c."""
        out = np.zeros(len(own))
        for k, (p, b) in enumerate(zip(self.parts, self.books)):
            r = b[codes[:, k]]
            out += (r * r).sum(axis=1) + 2 * (r * self.coarse[own][:, p]).sum(axis=1)
        return out

    def tables(self, q: np.ndarray) -> np.ndarray:
        """-2 q.r for every code of every sub-space and each query: (queries, sub_spaces, codes)."""
        out = np.zeros((len(q), len(self.parts), max(map(len, self.books))))
        for k, (p, b) in enumerate(zip(self.parts, self.books)):
            out[:, k, :len(b)] = -2 * q[:, p] @ b.T
        return out


def build(df: DataFrame, id_col: str = "vec_id", vec_col: str = "embedding", s: IndexSettings = IndexSettings()) -> tuple[DataFrame, Quantizer | None]:
    """Index (vec_id, list, codes, v) of every usable row, written to the shared folder, and the fitted quantizer.

    Vectors whose dimension is not the sample's most frequent one get list -1 and are always compared exactly.
    """
    d = usable(df, id_col, vec_col, zero=False)
    rows = d.count()
    s = fitted_to(s, rows)
    sample = [np.array(r.v) for r in d.orderBy(F.xxhash64("vec_id"), "vec_id").limit(s.sample_rows).collect()]
    if not sample:
        return df.sparkSession.createDataFrame([], SCHEMA), None
    dims = sorted(len(v) for v in sample)
    dim = max(set(dims), key=dims.count)
    quantizer = Quantizer(np.array([v for v in sample if len(v) == dim]), s)

    def run(batches):
        for b in batches:
            x, at = matrix(b.column(1), quantizer.dim)
            lists, codes, bias = np.full(b.num_rows, -1, np.int32), [b""] * b.num_rows, np.zeros(b.num_rows)
            if len(x):
                own, c = quantizer.encode(x)
                lists[at], bias[at] = own, quantizer.bias(own, c)
                for i, row in zip(at, c):
                    codes[i] = row.tobytes()
            yield pa.RecordBatch.from_arrays([b.column(0), pa.array(lists), pa.array(codes, pa.binary()), pa.array(bias), b.column(1)],
                                             names=["vec_id", "list", "codes", "bias", "v"])

    coded = d.mapInArrow(tidy(run), SCHEMA).repartitionByRange(max(1, math.ceil(rows / s.rows_per_task)), "list", "vec_id").sortWithinPartitions("list", "vec_id")
    index, _ = staged(coded, "ivf")
    return index, quantizer


FOUND = "query_id long, vec_id long, rough double, score double"


class _Shortlists:
    """The `size` best rows of every query by rough distance, ties to smaller ids, gathered piece by piece."""

    def __init__(self, queries: int, size: int):
        self.size, self.bar, self.rows, self.held = size, np.full(queries, np.inf), [np.zeros((4, 0))], 0

    def add(self, query: np.ndarray, ids: np.ndarray, rough: np.ndarray, score: np.ndarray) -> None:
        self.rows.append(np.stack([query.astype(np.float64), ids.view(np.float64), rough, score]))
        self.held += len(query)
        if self.held > 4 * self.size * len(self.bar):
            self.prune()

    def prune(self) -> tuple:
        query, ids, rough, score = np.concatenate(self.rows, axis=1)
        query, ids = query.astype(np.int64), np.ascontiguousarray(ids).view(np.int64)
        order = np.lexsort((ids, rough, query))
        query, ids, rough, score = query[order], ids[order], rough[order], score[order]
        place = np.arange(len(query)) - np.searchsorted(query, query)
        full = place == self.size - 1
        self.bar[query[full]] = rough[full]
        keep = place < self.size
        query, ids, rough, score = query[keep], ids[keep], rough[keep], score[keep]
        self.rows, self.held = [np.stack([query.astype(np.float64), ids.view(np.float64), rough, score])], len(query)
        return query, ids, rough, score


def _search_block(index: DataFrame, quantizer: Quantizer, ids: np.ndarray, vectors: list, s: IndexSettings) -> DataFrame:
    """FOUND: of each task, every query's s.rerank best rows by distance tables, with their exact distances."""
    same = np.flatnonzero([len(q) == quantizer.dim for q in vectors])
    q = np.array([vectors[n] for n in same]).reshape(-1, quantizer.dim)

    def run(batches):
        far = _squared(q, quantizer.coarse)
        probed = np.zeros(far.shape, dtype=bool)
        np.put_along_axis(probed, np.argsort(far, axis=1, kind="stable")[:, :math.ceil(s.probes * len(quantizer.coarse))], True, axis=1)
        tables, best = quantizer.tables(q), _Shortlists(len(vectors), s.rerank)
        for b in batches:
            if not b.num_rows:
                continue
            own, lists = b.column(0).to_numpy(), b.column(1).to_numpy()
            x, at = matrix(b.column(4), quantizer.dim)
            x_ids, x_list, bias = own[at], lists[at], b.column(3).to_numpy()[at]
            codes = np.frombuffer(b"".join(b.column(2).to_pylist()), np.uint8).reshape(len(at), len(quantizer.parts))
            for one in np.unique(x_list):
                m, of_list = np.flatnonzero(probed[:, one]), np.flatnonzero(x_list == one)
                for r in (of_list[k:k + 1024] for k in range(0, len(of_list), 1024) if len(m)):
                    rough = far[m, one][:, None] + bias[r]
                    for k in range(len(quantizer.parts)):
                        rough += tables[m, k][:, codes[r, k]]
                    good = (rough <= best.bar[same[m]][:, None]) & (x_ids[r] != ids[same[m]][:, None])
                    if len(r) > s.rerank:
                        rough[~good] = np.inf
                        order = np.argsort(rough, axis=1, kind="stable")[:, s.rerank:]
                        np.put_along_axis(good, order, False, axis=1)
                    i, j = np.nonzero(good)
                    best.add(same[m[i]], x_ids[r[j]], rough[i, j], np.sqrt(((x[r[j]] - q[m[i]]) ** 2).sum(axis=1)))
            for i in np.flatnonzero(lists == -1):  # of other dimensions: compared exactly
                p = np.array(b.column(4)[int(i)].as_py())
                n = np.array([n for n, v in enumerate(vectors) if len(v) == len(p) and ids[n] != own[i]], dtype=np.int64)
                d = np.array([float(np.sqrt(((p - vectors[k]) ** 2).sum())) for k in n])
                best.add(n, np.full(len(n), own[i]), d * d, d)
        query, found, rough, score = best.prune()
        yield pa.RecordBatch.from_arrays([pa.array(ids[query]), pa.array(found), pa.array(rough), pa.array(score)], names=[c.split()[0] for c in FOUND.split(", ")])

    return index.select("vec_id", "list", "codes", "bias", "v").mapInArrow(tidy(run), FOUND)


def _complete_block(index: DataFrame, quantizer: Quantizer, ids: np.ndarray, vectors: list, radius: np.ndarray, k: int) -> DataFrame:
    """FOUND: of each task, every query's k nearest rows within its radius, ties to smaller ids; rough is the score.

    What cannot be told for numbers that overflow is verified, so each test is for rows that are surely farther.
    """
    same = np.flatnonzero([len(q) == quantizer.dim for q in vectors])
    q = np.array([vectors[n] for n in same]).reshape(-1, quantizer.dim)

    def run(batches):
        with np.errstate(all="ignore"):
            far, tables, best = np.sqrt(_squared(q, quantizer.coarse)), quantizer.tables(q), _Shortlists(len(vectors), k)
            best.bar[:] = radius
            q_size = np.sqrt((q * q).sum(axis=1))
            for b in batches:
                if not b.num_rows:
                    continue
                own, lists = b.column(0).to_numpy(), b.column(1).to_numpy()
                x, at = matrix(b.column(4), quantizer.dim)
                x_ids, x_list, bias = own[at], lists[at], b.column(3).to_numpy()[at]
                codes = np.frombuffer(b"".join(b.column(2).to_pylist()), np.uint8).reshape(len(at), len(quantizer.parts))
                for one in np.unique(x_list):
                    of_list = np.flatnonzero(x_list == one)
                    for r in (of_list[j:j + 1024] for j in range(0, len(of_list), 1024)):
                        left = x[r] - quantizer.coarse[one]
                        reach = np.sqrt((left * left).sum(axis=1))
                        slack = 1e-6 * (q_size + np.sqrt((x[r] * x[r]).sum(axis=1)).max() + np.sqrt((quantizer.coarse[one] ** 2).sum()))
                        m = np.flatnonzero(~(far[:, one] - reach.max() > best.bar[same] + slack))
                        if not len(m):
                            continue
                        rough = far[m, one][:, None] ** 2 + bias[r]
                        decoded = np.concatenate([book[codes[r, n]] for n, book in enumerate(quantizer.books)], axis=1)
                        for n in range(len(quantizer.parts)):
                            rough += tables[m, n][:, codes[r, n]]
                        error = np.sqrt(((left - decoded) ** 2).sum(axis=1))
                        bar = (best.bar[same[m]] + slack[m])[:, None]
                        low = np.sqrt(np.maximum(rough, 0))  # nan stays, and is verified
                        good = ~(low - error > bar + np.sqrt(1e-12) * slack[m][:, None]) & (x_ids[r] != ids[same[m]][:, None])
                        good &= ~(np.sqrt(_squared(q[m], x[r])) > bar)
                        i, j = np.nonzero(good)
                        d = np.sqrt(((x[r[j]] - q[m[i]]) ** 2).sum(axis=1))
                        keep = ~(d > best.bar[same[m[i]]])
                        i, j, d = i[keep], j[keep], d[keep]
                        best.add(same[m[i]], x_ids[r[j]], d, d)
                for i in np.flatnonzero(lists == -1):  # of other dimensions
                    p = np.array(b.column(4)[int(i)].as_py())
                    n = np.array([n for n, v in enumerate(vectors) if len(v) == len(p) and ids[n] != own[i]], dtype=np.int64)
                    d = np.array([float(np.sqrt(((p - vectors[k]) ** 2).sum())) for k in n])
                    best.add(n, np.full(len(n), own[i]), d, d)
            query, found, rough, score = best.prune()
        yield pa.RecordBatch.from_arrays([pa.array(ids[query]), pa.array(found), pa.array(rough), pa.array(score)], names=[c.split()[0] for c in FOUND.split(", ")])

    return index.select("vec_id", "list", "codes", "bias", "v").mapInArrow(tidy(run), FOUND)


def _nearest_block(index: DataFrame, quantizer: Quantizer, ids: np.ndarray, vectors: list, s: IndexSettings, k: int) -> DataFrame:
    """_complete_block with the radius that the lists nearest to each query give; the driver holds one number per query of the block."""
    found, path = staged(_search_block(index, quantizer, ids, vectors, s), "ivf-near")
    rank = F.row_number().over(Window.partitionBy("query_id").orderBy("score"))
    at = {r.query_id: r.score for r in found.withColumn("n", rank).where(F.col("n") == k).collect()}
    discard(index.sparkSession, path)
    double = {i for i, n in zip(*np.unique(ids, return_counts=True)) if n > 1}  # two queries of one id: both look at all rows
    return _complete_block(index, quantizer, ids, vectors, np.array([np.inf if i in double else at.get(int(i), np.inf) for i in ids]), k)


def nearest(df: DataFrame, every: int = 100, k: int = K, id_col: str = "vec_id", vec_col: str = "embedding", s: IndexSettings = IndexSettings()) -> DataFrame:
    """query_id, rank, vec_id, score: the k nearest rows of each query, by Euclidean distance.

    Queries are rows whose id is divisible by `every`; candidates are all rows with another id.  Ties go to the smaller id;
    repeated rows are candidates each, and queries once.  Null ids, and vectors that are null, empty, zero or hold null or
    non-finite values take no part.  Vectors of different dimensions are never compared.
    """
    index, quantizer = build(df, id_col, vec_col, s)
    found = None
    if quantizer is not None:
        queries = index.where(F.col("vec_id") % every == 0).select("vec_id", "v").distinct()
        found = by_block(queries, s.query_block, lambda ids, vectors: _nearest_block(index, quantizer, ids, vectors, s, k))
    if found is None:
        return df.sparkSession.createDataFrame([], "query_id long, rank int, vec_id long, score double")
    exact = Window.partitionBy("query_id").orderBy("score", "vec_id")
    return found.withColumn("rank", F.row_number().over(exact)).where(F.col("rank") <= k).select("query_id", "rank", "vec_id", "score")
