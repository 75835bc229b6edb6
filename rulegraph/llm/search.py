"""Exact top-k inner products by pivot-table elimination.

For integer vectors the inner product is (|q|^2 + |x|^2 - d(q,x)^2) / 2, so a lower
bound of the distance bounds the score from above. Each task keeps a table of its
candidates' distances to many pivots; the largest |d(q,p) - d(x,p)| over pivots is a
lower bound of d(q,x). Candidates are evaluated in the order of their bounds, in
growing runs, until no bound reaches the k-th best score.

Queries (bounded blocks) go to every candidate partition; each returns its k best,
and a second stage keeps the k best of those.
"""

from __future__ import annotations

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame, Window
from pyspark.sql import functions as F

from .common import staged, tidied

_OUT = pa.schema([("query_id", pa.int64()), ("query_row", pa.int64()), ("vec_id", pa.int64()), ("score", pa.int64())])
#: Sums of squares below this are exact in float64.
EXACT = 1 << 53


def quantised(df: DataFrame, scale: int = 256) -> DataFrame:
    """(vec_id, v array<double>): floor(scale * x); vectors null, or with null or non-finite components, drop out."""
    x = F.transform(F.col("embedding"), lambda c: c.cast("double"))
    sound = F.forall(x, lambda c: c.isNotNull() & ~F.isnan(c) & (F.abs(c) < F.lit(float("inf"))))
    return df.select(F.col("vec_id").cast("long").alias("vec_id"), x.alias("x")).where(F.col("vec_id").isNotNull() & F.col("x").isNotNull() & sound).select("vec_id", F.transform("x", lambda c: F.floor(c * scale).cast("double")).alias("v"))


def _matrices(batch: pa.RecordBatch):
    """Vectors of a batch by dimension: (ids, rows)."""
    ids = batch.column(0).to_numpy()
    lists = batch.column(1)
    sizes = np.diff(np.asarray(lists.offsets))
    flat = lists.flatten().to_numpy(zero_copy_only=False)
    ends = np.cumsum(sizes)
    for n in np.unique(sizes):
        at = np.flatnonzero(sizes == n)
        yield int(n), ids[at], flat[((ends[at] - n)[:, None] + np.arange(n)).ravel()].reshape(len(at), n)


def choose_pivots(vectors: np.ndarray, count: int) -> np.ndarray:
    """Farthest-first pivots: the first row, then always the row farthest from those chosen."""
    chosen = [0]
    gap = ((vectors - vectors[0]) ** 2).sum(1)
    while len(chosen) < min(count, len(vectors)):
        k = int(gap.argmax())
        if gap[k] == 0:
            break
        chosen.append(k)
        gap = np.minimum(gap, ((vectors - vectors[k]) ** 2).sum(1))
    return vectors[chosen]


def _distances(a: np.ndarray, b: np.ndarray) -> np.ndarray:
    return np.sqrt(np.maximum((a * a).sum(1)[:, None] + (b * b).sum(1)[None] - 2 * a @ b.T, 0))


class PivotTable:
    """Candidates of one partition with their distances to pivots."""

    def __init__(self, ids: np.ndarray, vectors: np.ndarray, pivots: int = 16):
        order = np.argsort(ids, kind="stable")
        self.ids, self.vectors = ids[order], vectors[order]
        self.norms = (self.vectors**2).sum(1)
        self.pivots = choose_pivots(self.vectors, pivots)
        self.table = _distances(self.vectors, self.pivots)
        self.evaluated = 0

    def bounds(self, query: np.ndarray) -> np.ndarray:
        """Upper bounds of the scores of all candidates (with a margin for rounding)."""
        gap = np.abs(self.table - _distances(query[None], self.pivots)).max(1)
        gap = np.maximum(gap - 1e-6 * (1 + gap), 0)
        return (query @ query + self.norms - gap * gap) / 2 + 1

    def top(self, query_id: int, query: np.ndarray, k: int, first_run: int = 64) -> list[tuple[int, int]]:
        """The k best (score, id), ties to the smaller id; exact."""
        bound = self.bounds(query)
        own = np.flatnonzero(self.ids != query_id)
        run, ids, scores, left = first_run, np.zeros(0, np.int64), np.zeros(0), own
        while len(left):
            if len(left) > run:
                part = np.argpartition(-bound[left], run - 1)
                now, left = left[part[:run]], left[part[run:]]
            else:
                now, left = left, left[:0]
            self.evaluated += len(now)
            ids = np.concatenate([ids, self.ids[now]])
            scores = np.concatenate([scores, self.vectors[now] @ query])
            best = np.lexsort((ids, -scores))[:k]
            ids, scores = ids[best], scores[best]
            if len(ids) == k:
                left = left[bound[left] >= scores[-1]]
            run *= 2
        return [(int(s), int(i)) for s, i in zip(scores, ids, strict=True)]


def top_k(vectors: DataFrame, queries: DataFrame, k: int = 5, scale: int = 256, pivots: int = 16, block: int = 16384, rows_at_once: int = 65536) -> DataFrame:
    """The k largest integer inner products of each query with all other vectors.

    ``vectors`` and ``queries`` have vec_id and embedding. Returns query_id, rank (from
    1), vec_id, score; fewer rows where there are fewer candidates; ties go to the
    smaller vec_id. Only vectors of one dimension are compared. Rows that repeat a vec_id are
    vectors of their own: as queries each has k rows, as candidates each counts, but none counts for
    a query of its own id. Sums of squares of quantised vectors must stay under 2**53
    (else the task fails rather than rounding).

    Queries are taken in blocks of about ``block`` rows, one after the other: what the driver
    holds and what is sent to tasks at a time is bounded (block * dimension * 8 bytes),
    and the number of passes grows with the query set. With several blocks the quantised
    vectors and each block's answers are written once and the block is let go.
    """
    candidates, asked = quantised(vectors, scale), quantised(queries, scale)
    blocks = max(1, -(-asked.count() // block))
    if blocks == 1:
        found, _ = _answers(candidates, asked, 0, k, pivots, rows_at_once)
    else:
        candidates, asked, found = staged(candidates, "vectors"), staged(asked, "queries"), None
        for b in range(blocks):
            own = asked.where(F.pmod(F.xxhash64("vec_id"), F.lit(blocks)) == b)
            part, sent = _answers(candidates, own, b, k, pivots, rows_at_once)
            part = staged(part, "answers")
            sent.unpersist()
            found = part if found is None else found.unionByName(part)
    order = Window.partitionBy("query_id", "query_row").orderBy(F.desc("score"), "vec_id")
    return found.withColumn("rank", F.row_number().over(order)).where(F.col("rank") <= k).select("query_id", "rank", "vec_id", "score")


def _answers(candidates: DataFrame, asked: DataFrame, number: int, k: int, pivots: int, rows_at_once: int):
    """(query_id, query_row, vec_id, score): the k best of each task for one block of queries, and the broadcast block."""
    own: dict[int, tuple[list, list, list]] = {}
    seen = 0
    for batch in asked.toArrow().combine_chunks().to_batches():
        for n, ids, rows in _matrices(batch):
            held = own.setdefault(n, ([], [], []))
            held[0].append(ids)
            held[1].append((number << 32) + seen + np.arange(len(ids)))
            held[2].append(rows)
            seen += len(ids)
    sent = candidates.sparkSession.sparkContext.broadcast({n: tuple(np.concatenate(x) for x in parts) for n, parts in own.items()})

    def scan(batches):
        held: dict[int, list] = {}
        count = 0

        def flush():
            for n, found in held.items():
                if n not in sent.value:
                    continue
                ids, places, asks = sent.value[n]
                table = PivotTable(np.concatenate([x for x, _ in found]), np.concatenate([x for _, x in found]), pivots)
                if n and n * float(max(np.abs(table.vectors).max(), np.abs(asks).max())) ** 2 >= EXACT:
                    raise ValueError("a sum of squares of quantised components is 2**53 or more")
                out = [(int(q), int(p), i, s) for q, p, v in zip(ids, places, asks, strict=True) for s, i in table.top(int(q), v, k)]
                if out:
                    yield pa.RecordBatch.from_arrays([pa.array(c, pa.int64()) for c in zip(*out, strict=True)], schema=_OUT)
            held.clear()

        for batch in batches:
            for n, ids, rows in _matrices(batch):
                held.setdefault(n, []).append((ids, rows))
                count += len(ids)
            if count >= rows_at_once:
                yield from flush()
                count = 0
        yield from flush()

    return candidates.mapInArrow(tidied(scan), "query_id long, query_row long, vec_id long, score long"), sent
