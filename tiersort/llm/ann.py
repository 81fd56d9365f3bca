"""Approximate nearest neighbours by cosine: inverted file with product-quantised residuals.

Unit vectors are assigned to coarse centroids; the residual is cut into parts
and each part is named by the nearest of 256 codewords. A query visits the
lists of its nearest centroids. In each list the distances to all members are
sums of table entries (asymmetric distance: query exact, members quantised);
the most promising members are reranked by the exact cosine of the original
vectors. A member's code comes with its distance from what the code stands
for, so the table's distance and that error bound the true one: every member
whose bound lies within the k-th best exact distance is reranked too, and a
visited list loses none of its nearest. Centroids and codewords are fitted on a bounded sample (``most_fit``
vectors, by a hash of their ids); every vector is indexed.

How many lists there are and how many of them a query visits follows from a
trial: up to ``MOST_TRIED`` of the queries, by a hash of their ids, are held
against all vectors. For several numbers of lists, up to the root of the
table's rows, their true neighbours say how many lists hold the wanted share of
them, and the cheapest such pair is taken. So data without structure is visited
widely, data in clusters list by list.

A list is cut into shards of a bounded number of vectors, and the queries that
visit it into blocks of a bounded number, both by a hash of the id; a task sees
one block and one shard. Queries are exchanged by list, never broadcast. A
shard's best are merged by partial rank before and after the exchange.

Vectors that are null, zero, of another dimension than the first, or hold null
or non-finite components take no part, neither as query nor as candidate. Null
ids take no part. Equal scores are ordered by the smaller id; equal codes are
considered in the order of their ids. A query has fewer rows if there are
fewer candidates; an empty table gives no row; other columns are ignored.
"""

from __future__ import annotations

from collections.abc import Iterator

import numpy as np
import pandas as pd
import pyarrow as pa
from pyspark.sql import DataFrame, Window
from pyspark.sql import functions as F

from tiersort.llm.common import shipped, staged

MOST_FIT, MOST_TRIED = 20_000, 300


def kmeans(x: np.ndarray, k: int, rng: np.random.Generator, rounds: int = 12) -> np.ndarray:
    """Centroids of at most k distinct points; Lloyd rounds from a random start."""
    k = min(k, len(x))
    c = x[rng.choice(len(x), k, replace=False)].copy()
    half = (x * x).sum(1)
    for _ in range(rounds):
        near = nearest(x, c)
        size = np.bincount(near, minlength=k)
        for j in range(x.shape[1]):
            c[:, j] = np.where(size > 0, np.bincount(near, x[:, j], k) / np.maximum(1, size), c[:, j])
        for lost in np.flatnonzero(size == 0):  # an empty cell takes a point far from its centroid
            far = int(np.argmax(half - 2 * (x * c[near]).sum(1) + (c[near] ** 2).sum(1)))
            c[lost], half[far] = x[far], -np.inf
    return c


def nearest(x: np.ndarray, c: np.ndarray) -> np.ndarray:
    out = np.empty(len(x), np.int64)
    norm = (c * c).sum(1)
    for at in range(0, len(x), 8192):
        out[at:at + 8192] = (norm - 2 * x[at:at + 8192] @ c.T).argmin(1)
    return out


class Index:
    """Coarse centroids, and codewords (parts, 256, width) of residuals; works on unit vectors."""

    def __init__(self, sample: np.ndarray, coarse: np.ndarray, parts: int, seed: int = 3):
        rng = np.random.default_rng(seed)
        self.parts = parts
        self.width = -(-sample.shape[1] // parts)
        self.coarse = coarse
        rest = self.cut(sample - self.coarse[nearest(sample, self.coarse)])
        self.words = [kmeans(np.ascontiguousarray(rest[:, p]), 256, rng, 8) for p in range(parts)]

    def cut(self, x: np.ndarray) -> np.ndarray:
        full = np.zeros((len(x), self.parts * self.width))
        full[:, :x.shape[1]] = x
        return full.reshape(len(x), self.parts, self.width)

    def encode(self, x: np.ndarray) -> tuple[np.ndarray, np.ndarray]:
        cell = nearest(x, self.coarse)
        rest = self.cut(x - self.coarse[cell])
        return cell, np.stack([nearest(rest[:, p], self.words[p]).astype(np.uint8) for p in range(self.parts)], 1)

    def visits(self, q: np.ndarray, probes: int) -> np.ndarray:
        """The nearest lists of each query."""
        score = q @ self.coarse.T - (self.coarse ** 2).sum(1) / 2
        probes = min(probes, score.shape[1])
        return np.argsort(-score, 1, kind="stable")[:, :probes]

    def errors(self, x: np.ndarray, cell: np.ndarray, codes: np.ndarray) -> np.ndarray:
        """Distance of each vector from what its list and its code stand for."""
        rest = self.cut(x - self.coarse[cell])
        return np.sqrt(sum(((rest[:, p] - self.words[p][codes[:, p]]) ** 2).sum(1) for p in range(self.parts)))

    def distances(self, q: np.ndarray, cell: int, codes: np.ndarray) -> np.ndarray:
        """Asymmetric distances, squared, of each query from the members of a list."""
        rest = self.cut(q - self.coarse[cell])
        dist = np.zeros((len(q), len(codes)), np.float32)
        for p in range(self.parts):
            table = ((rest[:, p, None, :] - self.words[p][None]) ** 2).sum(2).astype(np.float32)
            dist += table[:, codes[:, p]]
        return dist

    def promising(self, q: np.ndarray, cell: int, codes: np.ndarray, keep: int, dist: np.ndarray | None = None) -> np.ndarray:
        """For each query the members of a list with the smallest asymmetric distance, as row numbers; ties by row."""
        if keep >= len(codes):
            return np.tile(np.arange(len(codes)), (len(q), 1))
        dist = self.distances(q, cell, codes) if dist is None else dist
        bound = np.partition(dist, keep - 1, 1)[:, keep - 1]
        out = np.empty((len(q), keep), np.int64)
        for i, b in enumerate(bound):
            row = dist[i]
            sure = np.flatnonzero(row < b)
            out[i] = np.concatenate([sure, np.flatnonzero(row == b)[:keep - len(sure)]])
        return out


def usable(df: DataFrame, id_col: str, vec_col: str) -> DataFrame:
    """Rows (id, v) of the vectors that take part, as doubles."""
    v = F.col(vec_col).cast("array<double>")
    norm = F.aggregate(v, F.lit(0.0), lambda s, x: s + x * x)
    fine = F.col(id_col).isNotNull() & v.isNotNull() & F.forall(v, lambda x: x.isNotNull() & ~F.isnan(x) & (F.abs(x) < F.lit(float("inf")))) & (F.size(v) > 0)
    return df.where(fine).select(F.col(id_col).cast("long").alias("id"), v.alias("v")).where(F.exists("v", lambda x: x != 0))


def _matrix(column: pa.Array) -> np.ndarray:
    return column.flatten().to_numpy(zero_copy_only=False).reshape(len(column), -1)


def _unit(x: np.ndarray) -> np.ndarray:
    top = np.abs(x).max(1, keepdims=True)
    x = x / top
    return x / np.sqrt((x * x).sum(1, keepdims=True))


def probes_for(sample: np.ndarray, coarse: np.ndarray, asks: np.ndarray, owner: np.ndarray, near: np.ndarray, recall: float) -> tuple[int, float]:
    """Lists to visit so that the share ``recall`` of true neighbours is met, and the share of the sample's vectors in them.

    ``near`` has the true neighbours of the queries ``asks``, ``owner`` the number of their query.
    """
    cell = nearest(sample, coarse)
    order = np.argsort(-(asks @ coarse.T - (coarse ** 2).sum(1) / 2), 1, kind="stable")
    place = np.empty_like(order)
    np.put_along_axis(place, order, np.arange(order.shape[1])[None], 1)
    met = np.sort(place[owner, nearest(near, coarse)])
    probes = int(met[min(len(met) - 1, int(np.ceil(recall * len(met))))]) + 1 if len(met) else 1
    size = np.bincount(cell, minlength=len(coarse))
    return probes, float(size[order[:, :probes]].sum(1).mean() / len(sample))


def trial(vectors: DataFrame, asked: DataFrame, k: int, most: int = MOST_TRIED) -> tuple[np.ndarray, np.ndarray, np.ndarray] | None:
    """At most ``most`` of the queries ``asked`` (id, v), and their k nearest of all ``vectors``, by comparison with each: queries, numbers of queries, neighbours."""
    some = asked.orderBy(F.xxhash64("id"), "id").limit(most).toArrow()
    if not len(some):
        return None
    names, asks = some.column("id").to_numpy(), _unit(_matrix(some.column("v").combine_chunks()))

    def compare(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for b in batches:
            ids = b.column(0).to_numpy(zero_copy_only=False)
            score = asks @ _unit(_matrix(b.column(1))).T if b.num_rows else np.zeros((len(asks), 0))
            score[names[:, None] == ids[None]] = -np.inf
            keep = min(k, b.num_rows)
            top = np.argpartition(-score, keep - 1, 1)[:, :keep] if keep else np.zeros((len(asks), 0), np.int64)
            owner = np.repeat(np.arange(len(asks), dtype=np.int32), keep)
            yield pa.RecordBatch.from_arrays([pa.array(owner), pa.array(score[owner, top.ravel()]), b.column(0).take(pa.array(top.ravel())), b.column(1).take(pa.array(top.ravel()))], names=["query_id", "score", "vec_id", "v"])

    found = vectors.mapInArrow(compare, "query_id int, score double, vec_id long, v array<double>").where(F.col("score") > float("-inf"))
    best = _best(found, k).select("query_id", "v").toArrow()  # k rows for each of the queries
    return asks, best.column("query_id").to_numpy(), _unit(_matrix(best.column("v").combine_chunks())) if len(best) else asks[:0]


def fit(vectors: DataFrame, asked: DataFrame, lists: int | None = None, parts: int = 16, most_fit: int = MOST_FIT, k: int = 5, recall: float = 0.96) -> tuple[Index, int] | None:
    """Index of rows (id, v) from at most ``most_fit`` of them, and the lists that queries ``asked`` (rows of the same form) are to visit.

    ``lists`` fixes the number of lists; without it the cheapest of several
    numbers is taken, up to the root of the rows and an eighth of the sample.
    """
    few = vectors.orderBy(F.xxhash64("id"), "id").limit(most_fit).toArrow()
    tried = trial(vectors, asked, k)
    if not len(few) or tried is None:
        return None
    x = _unit(_matrix(few.column("v").combine_chunks()))
    rows = vectors.count()
    most = max(8, min(int(rows ** 0.5), len(x) // 8))
    best = None
    for n in [lists] if lists else sorted({min(most, n) for n in (12, *(8 << j for j in range(14)))}):
        coarse = kmeans(x, n, np.random.default_rng(3))
        probes, share = probes_for(x, coarse, *tried, recall)
        cost = share + len(coarse) / rows  # members a query is held against, and centroids, by the table's size
        if best is None or cost < best[0]:
            best = cost, coarse, probes
    return Index(x, best[1], parts), best[2]


def search(df: DataFrame, is_query, id_col: str = "vec_id", vec_col: str = "embedding", k: int = 5, recall: float = 0.96, probes: float | None = None, rerank: int = 48,
           lists: int | None = None, parts: int = 16, shard_rows: int = 20_000, block_rows: int = 4_000, most_fit: int = MOST_FIT) -> DataFrame:
    """Rows (query_id, rank, vec_id, score): the k nearest found of each row with ``is_query`` (a condition on ``id``).

    ``recall`` is what the visited lists are to hold of the tried queries' true
    neighbours; ``probes`` fixes the share of lists a query visits instead.
    ``rerank`` members of each shard of a list are reranked first, then all
    whose bound is below the k-th of these. Rows that repeat an id count once, by their best vector.
    """
    spark = df.sparkSession
    empty = "query_id long, rank int, vec_id long, score double"
    every = usable(df, id_col, vec_col)
    head = every.select("id", F.size("v").alias("d")).groupBy("d").agg(F.min("id").alias("first")).orderBy("first").first()
    if head is None:
        return spark.createDataFrame([], empty)
    every = every.where(F.size("v") == head.d)
    fitted = fit(every, every.where(is_query), lists, parts, most_fit, k, recall)
    if fitted is None:
        return spark.createDataFrame([], empty)
    index, visited = fitted
    if probes is not None:
        visited = max(8, round(probes * len(index.coarse)))
    sent = shipped(spark, index)  # bounded: centroids and codewords only

    def encode(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        held = sent()
        for b in batches:
            if b.num_rows:
                x = _unit(_matrix(b.column(1)))
                cell, codes = held.encode(x)
                yield pa.RecordBatch.from_arrays([b.column(0), b.column(1), pa.array(cell.astype(np.int32)), pa.array([c.tobytes() for c in codes], pa.binary()), pa.array(held.errors(x, cell, codes))],
                                                 names=["id", "v", "list", "code", "error"])

    def visit(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        held = sent()
        for b in batches:
            if b.num_rows:
                lists_ = held.visits(_unit(_matrix(b.column(1))), visited)
                yield pa.RecordBatch.from_arrays([b.column(0), b.column(1), pa.array([x.astype(np.int32) for x in lists_], pa.list_(pa.int32()))], names=["id", "v", "lists"])

    coded = staged(every.mapInArrow(encode, "id long, v array<double>, list int, code binary, error double"), "coded")
    asked = staged(coded.where(is_query).select("id", "v").mapInArrow(visit, "id long, v array<double>, lists array<int>").select("id", "v", F.explode("lists").alias("list")), "asked")
    cut = lambda n, rows: F.greatest(F.lit(1), F.ceil(n / rows)).cast("int")
    sizes = (coded.groupBy("list").agg(cut(F.count("*"), shard_rows).alias("shards"))
             .join(asked.groupBy("list").agg(cut(F.count("*"), block_rows).alias("blocks")), "list"))  # a row for each centroid
    part = lambda of, n: F.pmod(F.xxhash64(of), F.col(n)).cast("int")
    every_part = lambda n: F.explode(F.sequence(F.lit(0), F.col(n) - 1))
    members = coded.join(F.broadcast(sizes), "list").withColumn("shard", part("id", "shards")).withColumn("block", every_part("blocks"))
    asked = asked.join(F.broadcast(sizes), "list").withColumn("block", part("id", "blocks")).withColumn("shard", every_part("shards"))

    def scan(key: tuple, q: pd.DataFrame, m: pd.DataFrame) -> pd.DataFrame:
        if not len(q) or not len(m):
            return pd.DataFrame({"query_id": pd.Series([], dtype="int64"), "vec_id": pd.Series([], dtype="int64"), "score": pd.Series([], dtype="float64")})
        held = sent()
        m = m.sort_values("id", kind="stable")
        ids, vecs = m["id"].to_numpy(), _unit(np.stack(m["v"].to_numpy()))
        codes = np.frombuffer(b"".join(m["code"]), np.uint8).reshape(len(m), -1)
        error = m["error"].to_numpy().astype(np.float32)
        out, slack = [], np.float32(1e-5)  # of the tables' single precision, in squares
        for at in range(0, len(q), 256):
            some = q.iloc[at:at + 256]
            mine, asks = some["id"].to_numpy(), _unit(np.stack(some["v"].to_numpy()))
            dist = held.distances(asks, int(key[0]), codes)
            rows = held.promising(asks, int(key[0]), codes, rerank + 1, dist)
            for i, r in enumerate(rows):
                r = r[ids[r] != mine[i]]
                exact = vecs[r] @ asks[i]
                if len(r) >= k and rerank + 1 < len(m):  # members that may be nearer than the k-th
                    far = np.sqrt(max(0.0, 2 - 2 * np.partition(exact, len(r) - k)[len(r) - k]))
                    open_ = dist[i] <= (np.float32(far) + error) ** 2 + slack
                    open_[rows[i]] = False
                    more = np.flatnonzero(open_)
                    more = more[ids[more] != mine[i]]
                    r, exact = np.concatenate([r, more]), np.concatenate([exact, vecs[more] @ asks[i]])
                exact = np.round(exact, 12)  # equal vectors get equal scores, wherever they stand in a block
                best = np.lexsort((ids[r], -exact))[:4 * k]  # some more: the last digits are settled below
                out.append(pd.DataFrame({"query_id": mine[i], "vec_id": ids[r][best], "score": exact[best]}))
        return pd.concat(out)

    found = asked.select("list", "shard", "block", "id", "v").groupBy("list", "shard", "block").cogroup(
        members.select("list", "shard", "block", "id", "v", "code", "error").groupBy("list", "shard", "block")).applyInPandas(scan, "query_id long, vec_id long, score double")
    top = _best(found.groupBy("query_id", "vec_id").agg(F.max("score").alias("score")), 4 * k)
    # the score in its plain form, over the components in order
    pairs = (top.join(coded.select(F.col("id").alias("query_id"), F.col("v").alias("a")), "query_id")
             .join(coded.select(F.col("id").alias("vec_id"), F.col("v").alias("b")), "vec_id"))
    dot = lambda x, y: F.aggregate(F.zip_with(x, y, lambda s, t: s * t), F.lit(0.0), lambda s, t: s + t)
    cosine = dot("a", "b") / (F.sqrt(dot("a", "a")) * F.sqrt(dot("b", "b")))
    scored = pairs.select("query_id", "vec_id", cosine.alias("score")).groupBy("query_id", "vec_id").agg(F.max("score").alias("score"))
    return _best(scored, k).select("query_id", "rank", "vec_id", "score")


def _best(found: DataFrame, k: int) -> DataFrame:
    """The k best of each query with their rank; rows beyond it go before the exchange."""
    order = Window.partitionBy("query_id").orderBy(F.desc("score"), "vec_id")
    return found.withColumn("rank", F.row_number().over(order)).where(F.col("rank") <= k)
