"""Packing by cutting-stock column generation.

Pieces are grouped into length classes (lengths rounded up to ``grain``), so the
linear program has at most capacity / grain rows whatever the corpus holds. Columns
are patterns (how many pieces of each class share a sequence); a knapsack dynamic
program prices new ones; the optimum is rounded down and the rest packed first-fit
decreasing. Pieces ranked within their class then take the patterns' places, class
by class. The driver sees the histogram and the patterns only.
"""

from __future__ import annotations

import zlib

import numpy as np
import pyarrow as pa
from pyspark import TaskContext
from pyspark.sql import DataFrame, Window
from pyspark.sql import functions as F

from .common import staged, tidied
from .word_ids import encoder, text_lists

_PIECES = pa.schema([("doc_id", pa.int64()), ("start", pa.int64()), ("length", pa.int64()), ("ids_crc32", pa.int64()), ("doc_tokens", pa.int64()), ("cls", pa.int32()), ("part", pa.int32()), ("inside", pa.int64())])
_PLACED = pa.schema([*list(_PIECES)[:5], ("sequence_id", pa.int64()), ("place", pa.int64())])
_PIECES_DDL = "doc_id long, start long, length long, ids_crc32 long, doc_tokens long, cls int, part int, inside long"


def best_pattern(values: np.ndarray, sizes: np.ndarray, room: int) -> tuple[float, np.ndarray]:
    """Unbounded knapsack: the pattern of largest value that fits into ``room``."""
    best = np.zeros(room + 1)
    choice = np.full(room + 1, -1)
    order = np.argsort(sizes)
    sorted_sizes, sorted_values = sizes[order], values[order]
    fits = np.searchsorted(sorted_sizes, np.arange(room + 1), "right")
    for c in range(1, room + 1):
        best[c], choice[c] = best[c - 1], -1
        if n := fits[c]:
            got = best[c - sorted_sizes[:n]] + sorted_values[:n]
            k = int(got.argmax())
            if got[k] > best[c] + 1e-12:
                best[c], choice[c] = got[k], k
    pattern, c = np.zeros(len(sizes)), room
    while c > 0:
        if choice[c] < 0:
            c -= 1
        else:
            pattern[order[choice[c]]] += 1
            c -= sorted_sizes[choice[c]]
    return float(best[room]), pattern


def plan_patterns(demand: dict[int, int], room: int, gap: float = 1e-3, max_columns: int = 5000) -> list[tuple[dict[int, int], int]]:
    """Patterns with counts whose places equal ``demand`` ({class size: pieces}) exactly.

    Column generation stops at the optimum or when the dual bound shows that at most
    the share ``gap`` of the sequences could still be saved.
    """
    sizes = np.array(sorted(s for s, n in demand.items() if n > 0), dtype=np.int64)
    if not len(sizes):
        return []
    need = np.array([demand[int(s)] for s in sizes], float)
    m = len(sizes)
    basis = np.diag((room // sizes).astype(float))
    inverse = np.diag(1.0 / (room // sizes))
    for step in range(max_columns):
        duals = inverse.sum(axis=0)
        value, column = best_pattern(duals, sizes, room)
        held = inverse @ need
        if value <= 1 + 1e-9 or held.sum() <= (duals @ need) / value * (1 + gap):
            break
        direction = inverse @ column
        usable = direction > 1e-9
        if not usable.any():
            break
        ratios = np.where(usable, held / np.where(usable, direction, 1), np.inf)
        leave = int(ratios.argmin())
        basis[:, leave] = column
        if step % 200 == 199:
            inverse = np.linalg.inv(basis)
        else:
            row = inverse[leave] / direction[leave]
            inverse -= np.outer(direction, row)
            inverse[leave] = row
    held = np.maximum(inverse @ need, 0)
    left, plan = need.astype(np.int64), []
    for k in np.argsort(-held, kind="stable"):
        pattern = np.rint(basis[:, k]).astype(np.int64)
        used = pattern > 0
        times = min(int(held[k] + 1e-9), int((left[used] // pattern[used]).min()))
        if times > 0:
            plan.append(({int(sizes[i]): int(pattern[i]) for i in np.flatnonzero(used)}, times))
            left -= times * pattern
    while left.any():
        pattern, space = np.zeros(m, np.int64), room
        for i in range(m - 1, -1, -1):
            pattern[i] = min(int(left[i]), space // int(sizes[i]))
            space -= int(pattern[i] * sizes[i])
        used = pattern > 0
        times = int((left[used] // pattern[used]).min())
        plan.append(({int(sizes[i]): int(pattern[i]) for i in np.flatnonzero(used)}, times))
        left -= times * pattern
    return plan


def _places(plan: list[tuple[dict[int, int], int]]) -> dict[int, tuple[np.ndarray, ...]]:
    """By class: first rank, copies in a sequence, first sequence and first place of each pattern."""
    rows: dict[int, list] = {}
    given: dict[int, int] = {}
    sequence = 0
    for pattern, times in plan:
        place = 0
        for size in sorted(pattern, reverse=True):
            copies = pattern[size]
            rows.setdefault(size, []).append((given.get(size, 0), copies, sequence, place))
            given[size] = given.get(size, 0) + copies * times
            place += copies
        sequence += times
    return {s: tuple(np.array(x, np.int64) for x in zip(*r, strict=True)) for s, r in rows.items()}


def pieces_of(docs: DataFrame, tokenizer: str, end_id: int = 2, room: int = 4096, grain: int = 16) -> DataFrame:
    """Every document cut into pieces of at most ``room`` ids, with class and rank in its task."""

    def cut(batches):
        coder, part = encoder(tokenizer), TaskContext.get().partitionId()
        seen = np.zeros(room // grain + 2, np.int64)
        for batch in batches:
            doc_ids = batch.column(0)
            for first, texts in text_lists(batch):
                ids, bounds = coder.encode(texts, end_id)
                ids = np.ascontiguousarray(ids, "<u4")
                sizes = np.diff(bounds)
                pieces = -(-sizes // room)
                doc = np.repeat(np.arange(len(texts)), pieces)
                nth = np.arange(len(doc)) - np.repeat(np.cumsum(pieces) - pieces, pieces)
                start = nth * room
                length = np.minimum(room, sizes[doc] - start)
                at = bounds[doc] + start
                view = memoryview(ids).cast("B")
                crc = np.fromiter((zlib.crc32(view[4 * a : 4 * (a + n)]) for a, n in zip(at.tolist(), length.tolist(), strict=True)), np.int64, len(doc))
                cls = -(-length // grain)
                order = np.argsort(cls, kind="stable")
                new = np.bincount(cls, minlength=len(seen))
                inside = np.empty(len(doc), np.int64)
                inside[order] = np.arange(len(doc)) - np.repeat(np.cumsum(new) - new, new) + np.repeat(seen, new)
                seen += new
                own = doc_ids.slice(first, len(texts)).take(pa.array(doc))
                yield pa.RecordBatch.from_arrays([own, pa.array(start), pa.array(length), pa.array(crc), pa.array(sizes[doc]), pa.array(cls.astype(np.int32)), pa.array(np.full(len(doc), part, np.int32)), pa.array(inside)], schema=_PIECES)

    return docs.select(F.col("doc_id").cast("long").alias("doc_id"), "text").mapInArrow(tidied(cut), _PIECES_DDL)


def pack(docs: DataFrame, tokenizer: str, end_id: int = 2, room: int = 4096, grain: int = 16) -> DataFrame:
    """Packs documents (doc_id, text) into sequences of at most ``room`` ids.

    Null and empty texts are the end id alone; repeated rows are packed each; an empty
    table gives no rows. Returns doc_id, start, length, ids_crc32, doc_tokens,
    sequence_id, offset: one row for each piece.
    """
    pieces = staged(pieces_of(docs, tokenizer, end_id, room, grain), "pieces")
    counts = pieces.groupBy("part", "cls").agg(F.count(F.lit(1)).alias("n"))
    demand = {r["cls"]: r["n"] for r in counts.groupBy("cls").agg(F.sum("n").alias("n")).collect()}
    places = _places(plan_patterns(demand, room // grain))
    before = Window.partitionBy("cls").orderBy("part").rowsBetween(Window.unboundedPreceding, -1)
    shifts = counts.select("part", "cls", F.coalesce(F.sum("n").over(before), F.lit(0)).alias("shift"))
    ranked = pieces.join(shifts, ["part", "cls"]).select("doc_id", "start", "length", "ids_crc32", "doc_tokens", "cls", (F.col("inside") + F.col("shift")).alias("rank"))

    def assign(batches):
        for batch in batches:
            cls, rank = batch.column(5).to_numpy(), batch.column(6).to_numpy()
            sequence, place = np.empty(len(cls), np.int64), np.empty(len(cls), np.int64)
            for c in np.unique(cls):
                at = cls == c
                first, copies, base, spot = places[int(c)]
                k = np.searchsorted(first, rank[at], "right") - 1
                step = rank[at] - first[k]
                sequence[at], place[at] = base[k] + step // copies[k], spot[k] + step % copies[k]
            yield pa.RecordBatch.from_arrays([*batch.columns[:5], pa.array(sequence), pa.array(place)], schema=_PLACED)

    placed = ranked.mapInArrow(tidied(assign), "doc_id long, start long, length long, ids_crc32 long, doc_tokens long, sequence_id long, place long")
    earlier = Window.partitionBy("sequence_id").orderBy("place").rowsBetween(Window.unboundedPreceding, -1)
    return placed.withColumn("offset", F.coalesce(F.sum("length").over(earlier), F.lit(0)).cast("long")).drop("place")
