"""Exact top-k inner products with MaxScore over sharded dimension postings.

A vector becomes integers floor(scale * x).  A query's terms are its dimensions; a term's score bound in a shard
is the largest product that any posting there can give.  With the threshold of the k-th best so far, terms are
taken as essential, largest bounds first, until the bounds of the others can't lift a candidate over it on their
own; scores are gathered over the essential postings, and the other terms are probed, strongest first, only for
candidates that are still competitive.  Shards are merged by score, then by smaller id.

Products may be negative, so each query is moved to the shard's lowest impact per dimension first; the moved
products are >= 0 and the moved part is a constant of the query.  Where a product could leave 64 bits, Python's whole
numbers are used; a score that doesn't fit the result's 64 bits is an error, not a wrong number.
"""

from __future__ import annotations

import math
from fractions import Fraction

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F
from pyspark.sql.window import Window

from binlens.llm.common import narrow, settle

SHARD = 8192  # vectors of one shard
QUERIES = 1024  # queries of one block


class Shard:
    def __init__(self, ids: np.ndarray, x: np.ndarray):
        order = np.argsort(ids, kind="stable")
        self.ids, self.x = ids[order], np.ascontiguousarray(x[order].T)  # one row of postings for each dimension
        self.low, self.high = self.x.min(axis=1), self.x.max(axis=1)

    def top(self, q: np.ndarray, own: int | None, k: int) -> tuple[np.ndarray, np.ndarray]:
        """Best ``k`` (ids, scores) for a query of integers; ``own`` is its own id, which is left out."""
        if not self._fits(q):
            return self._exact(q, own, k)
        base = np.where(q > 0, self.low, self.high)  # impact that gives the least product
        constant = int((q * base).sum())
        bound = q * (np.where(q > 0, self.high, self.low) - base)
        terms = np.argsort(-bound, kind="stable")
        terms = terms[bound[terms] > 0]
        n = len(self.ids)
        keep = np.ones(n, bool) if own is None else self.ids != own
        live = np.flatnonzero(keep)
        if not len(live):
            return self.ids[:0], self.ids[:0]
        rest = np.concatenate([np.cumsum(bound[terms][::-1])[::-1], [0]])  # bound of terms[i:]
        # first threshold: full scores of the vectors that lead on the strongest term
        lead = live if len(live) <= 4 * k or not len(terms) else live[np.argpartition(-(q[terms[0]] * self.x[terms[0], live]), 4 * k)[: 4 * k]]
        full = q @ self.x[:, lead] - constant
        floor = int(np.sort(full)[-k]) if len(full) >= k else -1
        essential = int(np.searchsorted(-rest, -floor, "left")) if floor > 0 else len(terms)
        essential = max(1, min(len(terms), essential)) if len(terms) else 0
        first = terms[:essential]
        score = (q[first] - 0) @ (self.x[first] - base[first][:, None]) if len(first) else np.zeros(n, np.int64)
        score = score[live]
        at = essential
        while True:
            fit = score + rest[at] >= floor
            live, score = live[fit], score[fit]
            if at >= len(terms):
                break
            step = terms[at : at + 8]
            score = score + q[step] @ (self.x[np.ix_(step, live)] - base[step][:, None])
            at += len(step)
            if len(score) > k:
                floor = max(floor, int(np.partition(score, len(score) - k)[len(score) - k]))
        order = np.lexsort((self.ids[live], -score))[:k]
        return self.ids[live[order]], score[order] + constant


    def _fits(self, q: np.ndarray) -> bool:
        """Whether sums of moved products stay within 64 bits."""
        if q.dtype == object or self.x.dtype == object:
            return False
        most = max(int(np.abs(self.low).max()), int(np.abs(self.high).max())) * int(np.abs(q).max())
        return 4 * len(q) * most < 1 << 62

    def _exact(self, q: np.ndarray, own: int | None, k: int) -> tuple[np.ndarray, np.ndarray]:
        ask, x = [int(a) for a in q], self.x.T.tolist()
        scored = sorted((-sum(a * int(b) for a, b in zip(ask, row)), i) for i, row in zip(self.ids.tolist(), x) if i != own)[:k]
        return np.array([i for _, i in scored], np.int64), np.array([-s for s, _ in scored], np.int64)


def integers(vectors: DataFrame, id_col: str, vector_col: str) -> DataFrame:
    """(vec_id, x array<double>) of the rows that take part: vectors that aren't null and hold finite numbers only."""
    x = F.transform(F.col(vector_col), lambda e: e.cast("double"))
    rows = vectors.select(F.col(id_col).cast("long").alias("vec_id"), x.alias("x")).where("vec_id is not null and x is not null and size(x) > 0")
    return rows.where("not exists(x, e -> e is null or isnan(e) or e = double('infinity') or e = double('-infinity'))")


def _packed(rows: DataFrame, size: int, key: str, scale: int) -> DataFrame:
    """Blocks of at most ``size`` vectors of one length, one row each, of 2 or 8 bytes a component: whole numbers, or
    (wide = 0) the doubles themselves where they are too large.  A small table is read by few tasks, so blocks are full."""
    rows = rows.coalesce(max(1, -(-rows.count() // size)))

    def run(batches):
        held: dict[int, tuple[list, list]] = {}

        def out(d):
            ids, v = held.pop(d)
            body = np.array(v, np.float64)
            with np.errstate(over="ignore"):
                whole = np.floor(scale * body)
            most = np.abs(whole).max(initial=0)
            wide = 2 if most < 1 << 15 else 8 if most < 1 << 53 else 0
            if wide:
                body = whole.astype(np.int64 if wide == 8 else np.int16)
            return pa.RecordBatch.from_arrays([pa.array([d], pa.int32()), pa.array([wide], pa.int32()), pa.array([np.array(ids, np.int64).tobytes()],
                pa.binary()), pa.array([body.tobytes()], pa.binary())], ["dim", "wide", "ids", "body"])

        for b in batches:
            for i, v in zip(b.column(0).to_pylist(), b.column(1).to_pylist()):
                one = held.setdefault(len(v), ([], []))
                one[0].append(i)
                one[1].append(v)
                if len(one[0]) >= size:
                    yield out(len(v))
        for d in list(held):
            yield out(d)

    return narrow(rows, run, "dim int, wide int, ids binary, body binary").withColumn(key, F.monotonically_increasing_id())


def _matrix(body: bytes, wide: int, dim: int, scale: int) -> np.ndarray:
    if wide:
        return np.frombuffer(body, np.int64 if wide == 8 else np.int16).astype(np.int64).reshape(-1, dim)
    exact = [math.floor(Fraction(x) * scale) for x in np.frombuffer(body, np.float64).tolist()]
    return np.array(exact, object).reshape(-1, dim)


def top_k(vectors: DataFrame, queries: DataFrame, k: int = 5, scale: int = 256, id_col: str = "vec_id", vector_col: str = "embedding") -> DataFrame:
    """query_id, rank, vec_id, score: the ``k`` highest integer inner products of each query with all other rows.

    Ties go to the smaller vec_id.  Null vectors, and those with null or non-finite components, take no part; a
    vector is compared with those of its length.  Repeated ids count as rows of their own, as candidates and as queries
    (each gives its own ``k`` rows), but none with the query's id is its candidate.  An empty side gives no rows.
    """
    spark = vectors.sparkSession
    own, asked = integers(vectors, id_col, vector_col), integers(queries, id_col, vector_col)
    shards = settle(_packed(own, SHARD, "shard", scale), "shards")
    blocks = settle(_packed(asked, QUERIES, "block", scale), "blocks")
    # shards and query blocks meet by block number: every shard is sent once to each block of about a thousand queries
    numbers = blocks.select("dim", "block").groupBy("dim").agg(F.collect_list("block").alias("meets"))
    pairs = shards.join(numbers, "dim").withColumn("block", F.explode("meets")).select("dim", "block", "shard", F.col("wide").alias("s_wide"),
        F.col("ids").alias("s_ids"), F.col("body").alias("s_body"))
    pairs = pairs.repartition(max(2, int(spark.conf.get("spark.sql.shuffle.partitions"))), "block", "shard").join(blocks, ["dim", "block"])

    def search(batches):
        for b in batches:
            for row in b.to_pylist():
                d = row["dim"]
                shard = Shard(np.frombuffer(row["s_ids"], np.int64), _matrix(row["s_body"], row["s_wide"], d, scale))
                q_ids, q = np.frombuffer(row["ids"], np.int64), _matrix(row["body"], row["wide"], d, scale)
                out: tuple[list, ...] = ([], [], [], [])
                for at, (i, v) in enumerate(zip(q_ids.tolist(), q)):
                    found, score = shard.top(v, i, k)
                    for held, new in zip(out, (np.full(len(found), i), np.full(len(found), (row["block"] << 10) + at), found, score)):
                        held.append(new)
                yield pa.RecordBatch.from_arrays([pa.array(np.concatenate(x).astype(np.int64)) for x in out], ["query_id", "query_row", "vec_id", "score"])

    found = narrow(pairs, search, "query_id long, query_row long, vec_id long, score long")
    order = Window.partitionBy("query_id", "query_row").orderBy(F.desc("score"), "vec_id")
    return found.withColumn("rank", F.row_number().over(order)).where(F.col("rank") <= k).select("query_id", "rank", "vec_id", "score")
