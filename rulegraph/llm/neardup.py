"""Near-duplicates: ProbMinHash signatures of weighted shingles, banding, verification.

Every text's word shingles (five words, weights are counts) get exponential arrivals:
the points of a Poisson process with the shingle's weight as rate, each sent to a
random register, which keeps the earliest point's shingle. Generation stops once no
further point can come before the latest register. Equal registers estimate the
probability Jaccard similarity; bands of registers propose candidates; a candidate
counts only after its exact similarity is computed from all shingles of both texts.

Plain Jaccard similarity counts as well, so texts that repeat shingles are signed a second
time with all weights 1. Both signatures share the bands' keys: for a text that repeats
nothing they are the same, so either kind of similarity is met by bands of its own.

Skew: texts with equal bytes are one node, however many copies there are. In a bucket
members are first compared with one leader, the member that shares most buckets with
others (the middle of a family of near copies). Buckets that still hold more than one
class are then settled by blocks: counts of shingles in cells bound what two members
can share from above, so they tell which members have any possible partner of another
class and never lose a pair; those are compared exactly, inside the task, skipping
pairs of one class. A large bucket is dealt out as pairs of blocks of bounded size, and
what leaves a task are the links of a spanning forest, never all pairs. Nothing is capped.
"""

from __future__ import annotations

import numpy as np
import pyarrow as pa
from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

from .common import blocks_of, free_name, mix64, shuffle_partitions, staged, tidied, words_of

#: Stands for a null doc_id inside joins.
_NO_ID = -(1 << 63)
_NODE = pa.schema([("doc_id", pa.int64()), ("node", pa.binary()), ("bands", pa.list_(pa.int64()))])
_SHINGLES = pa.schema([("node", pa.binary()), ("shingles", pa.binary()), ("weights", pa.binary()), ("cells", pa.binary())])
_CELLS = 128
_ODD = [np.uint64(x | 1) for x in (0x9E3779B97F4A7C15, 0xC2B2AE3D27D4EB4F, 0x165667B19E3779F9, 0x27D4EB2F165667C5, 0x85EBCA77C2B2AE63, 0xD6E8FEB86659FD93, 0xA0761D6478BD642F, 0xE7037ED1A0B428DB)]


def shingles_of(data: np.ndarray, offsets: np.ndarray, size: int = 5) -> tuple[np.ndarray, np.ndarray, np.ndarray]:
    """Distinct shingles of each text of a block: hashes and counts, ordered by text and hash, and bounds.

    A text with fewer words than ``size`` (but not none) is one shingle.
    """
    _, _, hashes, bounds = words_of(data, offsets)
    n = np.diff(bounds)
    count = np.where(n >= size, n - size + 1, (n > 0).astype(np.int64))
    text = np.repeat(np.arange(len(n)), count)
    first = bounds[:-1][text] + np.arange(len(text)) - np.repeat(np.cumsum(count) - count, count)
    left = bounds[1:][text] - first
    if not len(text):
        return np.zeros(0, np.uint64), np.zeros(0, np.int64), np.zeros(len(n) + 1, np.int64)
    padded = np.concatenate([hashes, np.zeros(size, np.uint64)])
    total = np.zeros(len(text), np.uint64)
    for j in range(size):
        own = padded[first + j] * _ODD[j % len(_ODD)] + np.uint64(j)
        total += own if j == 0 else np.where(j < left, own, np.uint64(0))
    total = mix64(total)
    order = np.argsort(total)
    # texts of a block are few: sorting them by a small integer keeps the order inside
    order = order[np.argsort(text[order].astype(np.uint16 if len(n) < 1 << 16 else np.int64), kind="stable")]
    text, total = text[order], total[order]
    new = np.concatenate([[True], (text[1:] != text[:-1]) | (total[1:] != total[:-1])])
    at = np.flatnonzero(new)
    weight = np.diff(np.concatenate([at, [len(text)]]))
    return total[at], weight, np.searchsorted(text[at], np.arange(len(n) + 1))


def signatures(shingles: np.ndarray, weights: np.ndarray, bounds: np.ndarray, registers: int = 80) -> np.ndarray:
    """ProbMinHash: for each text the shingle (low 32 bits of its hash) in each register; 0 where it has none.

    A register's key is the arrival time (as float bits, which order like positive
    numbers) above the shingle's bits, so the least key is the earliest arrival.
    Texts that hold many shingles first skip arrivals beyond a time by which all
    registers are almost surely filled; the few texts where they are not start over.
    """
    texts = len(bounds) - 1
    out = np.full(texts * registers, np.uint64(0xFFFFFFFFFFFFFFFF))
    owner = np.repeat(np.arange(texts), np.diff(bounds))
    mass = np.bincount(owner, weights, texts)
    likely = registers * (np.log(registers) + 8) / np.maximum(mass, 1)

    def run(live: np.ndarray, limit: np.ndarray) -> None:
        time = np.zeros(len(live))
        step = 0
        while len(live):
            seed = mix64(np.array([step + 1], np.uint64))[0]
            drawn = mix64(shingles[live] ^ seed)
            unit = (drawn >> np.uint64(11)).astype(np.float64) * (1.0 / (1 << 53))
            time = time - np.log1p(-unit) / weights[live]
            own = owner[live]
            keep = time < limit[own]
            live, time, own = live[keep], time[keep], own[keep]
            register = (mix64(drawn ^ np.uint64(0xA5A5A5A5A5A5A5A5)) >> np.uint64(32)) % np.uint64(registers)
            register = register[keep]
            key = (time.astype(np.float32).view(np.uint32).astype(np.uint64) << np.uint64(32)) | (shingles[live] & np.uint64(0xFFFFFFFF))
            np.minimum.at(out, own * registers + register.astype(np.int64), key)
            latest = out.reshape(texts, registers).max(1)
            full = latest != np.uint64(0xFFFFFFFFFFFFFFFF)
            latest_time = np.where(full, (latest >> np.uint64(32)).astype(np.uint32).view(np.float32).astype(np.float64), np.inf)
            keep = time <= np.minimum(latest_time, limit)[own]
            live, time = live[keep], time[keep]
            step += 1

    run(np.arange(len(shingles)), likely)
    short = (out.reshape(texts, registers).max(1) == np.uint64(0xFFFFFFFFFFFFFFFF)) & (mass > 0)
    if short.any():
        out.reshape(texts, registers)[short] = np.uint64(0xFFFFFFFFFFFFFFFF)
        run(np.flatnonzero(short[owner]), np.full(texts, np.inf))
    out = (out & np.uint64(0xFFFFFFFF)).astype(np.uint32).reshape(texts, registers)
    out[mass == 0] = 0
    return out


def band_keys(signature: np.ndarray, bands: int) -> np.ndarray:
    rows = signature.shape[1] // bands
    key = np.zeros((len(signature), bands), np.uint64)
    for j in range(rows):
        key += mix64(signature[:, j::rows][:, :bands].astype(np.uint64) + np.uint64(j << 34))
    return mix64(key * np.uint64(0x9E3779B97F4A7C15) + np.arange(bands, dtype=np.uint64)[None])


def similarity(a: np.ndarray, x: np.ndarray, b: np.ndarray, y: np.ndarray) -> float:
    """The larger of the probability Jaccard and the Jaccard similarity of two weighted sorted shingle sets.

    For equal weights both are the same.
    """
    if not len(a) or not len(b):
        return 0.0
    both, at, bt = np.intersect1d(a, b, assume_unique=True, return_indices=True)
    if not len(both):
        return 0.0
    plain = len(both) / (len(a) + len(b) - len(both))
    if (x == 1).all() and (y == 1).all():
        return plain
    p = np.concatenate([x[at], np.delete(x, at), np.zeros(len(b) - len(bt))]).astype(float)
    q = np.concatenate([y[bt], np.zeros(len(a) - len(at)), np.delete(y, bt)]).astype(float)
    ratio = np.where(p > 0, q / np.maximum(p, 1e-300), np.inf)
    order = np.argsort(ratio, kind="stable")
    sorted_ratio = ratio[order]
    below = np.concatenate([[0], np.cumsum(p[order])])
    above = np.concatenate([np.cumsum(q[order][::-1])[::-1], [0]])
    k = np.searchsorted(sorted_ratio, ratio[: len(both)], "right")
    return max(plain, float((1 / (below[k] / p[: len(both)] + above[k] / q[: len(both)])).sum()))


def with_nodes(docs: DataFrame) -> DataFrame:
    """(doc_id, node, text): node is the first half of the text's SHA-256; a null text is the empty text."""
    text = F.coalesce(F.col("text"), F.lit(""))
    return docs.select(F.col("doc_id").cast("long").alias("doc_id"), F.substring(F.unhex(F.sha2(text, 256)), 1, 16).alias("node"), text.alias("text"))


def all_bands(shingles: np.ndarray, weights: np.ndarray, bounds: np.ndarray, registers: int, bands: int) -> list[list[int]]:
    """Band keys of each text: by weights, then by shingles alone where some shingle repeats; none for a text without words."""
    own = band_keys(signatures(shingles, weights, bounds, registers), bands).view(np.int64)
    out = [keys if n else [] for keys, n in zip(own.tolist(), np.diff(bounds).tolist(), strict=True)]
    owner = np.repeat(np.arange(len(out)), np.diff(bounds))
    again = np.unique(owner[weights > 1])
    if len(again):
        mask = np.isin(owner, again)
        ends = np.concatenate([[0], np.cumsum(np.diff(bounds)[again])])
        plain = band_keys(signatures(shingles[mask], np.ones(int(mask.sum()), np.int64), ends, registers), bands).view(np.int64)
        for i, keys in zip(again.tolist(), plain.tolist(), strict=True):
            out[i] += keys
    return out


def signed_nodes(docs: DataFrame, registers: int, bands: int, size: int, block_bytes: int = 1 << 20) -> DataFrame:
    """(doc_id, node, bands) of texts (doc_id, node, text); a text without words has no bands."""

    def sign(batches):
        for batch in batches:
            for first, n, data, offsets in blocks_of(batch, limit=block_bytes):
                keys = all_bands(*shingles_of(data, offsets, size), registers, bands)
                yield pa.RecordBatch.from_arrays([batch.column(0).slice(first, n), batch.column(1).slice(first, n), pa.array(keys, pa.list_(pa.int64()))], schema=_NODE)

    return docs.mapInArrow(tidied(sign), "doc_id long, node binary, bands array<long>")


def cells_of(shingles: np.ndarray, weights: np.ndarray) -> np.ndarray:
    """How many shingles, and how much weight, fall in each cell of their hashes."""
    cell = (shingles >> np.uint64(32)).astype(np.int64) % _CELLS
    return np.concatenate([np.bincount(cell, minlength=_CELLS), np.bincount(cell, weights, _CELLS).astype(np.int64)]).astype(np.int32)


def may_reach(part: np.ndarray, cells: np.ndarray, threshold: float) -> np.ndarray:
    """Which texts of part and of all may be similar, by cells: false only where both similarities are below the threshold.

    Two texts share no more than the smaller count of each cell, and probability Jaccard is
    at most the smaller share of weight summed over cells. What is equal but for rounding passes.
    """
    a, b = part[:, :_CELLS].astype(np.float32), cells[:, :_CELLS].astype(np.float32)
    both = np.minimum(a[:, None], b[None]).sum(2, dtype=np.float64)
    plain = both >= (threshold - 1e-4) * (a.sum(1, dtype=np.float64)[:, None] + b.sum(1, dtype=np.float64)[None] - both)
    p, q = (x[:, _CELLS:] / np.maximum(x[:, _CELLS:].sum(1, keepdims=True, dtype=np.int64), 1) for x in (part, cells))
    return plain | (np.minimum(p.astype(np.float32)[:, None], q.astype(np.float32)[None]).sum(2) >= threshold - 1e-4)


def shingle_table(texts: DataFrame, size: int) -> DataFrame:
    """(node, shingles, weights, cells) as packed arrays of texts (node, text)."""

    def cut(batches):
        for batch in batches:
            for first, n, data, offsets in blocks_of(batch):
                shingles, weights, bounds = shingles_of(data, offsets, size)
                weights = weights.astype(np.int32)
                cuts = list(zip(bounds[:-1].tolist(), bounds[1:].tolist(), strict=True))
                cells = [cells_of(shingles[a:b], weights[a:b]).tobytes() for a, b in cuts]
                # weights that are all 1 are not written
                yield pa.RecordBatch.from_arrays([batch.column(0).slice(first, n), pa.array([shingles[a:b].tobytes() for a, b in cuts], pa.binary()), pa.array([b"" if (weights[a:b] == 1).all() else weights[a:b].tobytes() for a, b in cuts], pa.binary()), pa.array(cells, pa.binary())], schema=_SHINGLES)

    return texts.select("node", "text").mapInArrow(tidied(cut), "node binary, shingles binary, weights binary, cells binary")


def verified(pairs: DataFrame, shingles: DataFrame, threshold: float) -> DataFrame:
    """Pairs (a, b) of nodes whose exact similarity reaches the threshold."""
    schema = pa.schema([("a", pa.binary()), ("b", pa.binary())])

    def judge(batches):
        def unpack(value, weights):
            s = np.frombuffer(value, np.uint64)
            return s, np.frombuffer(weights, np.int32) if weights else np.ones(len(s), np.int32)

        for batch in batches:
            kept = [i for i, (s, x, t, y) in enumerate(zip(*(batch.column(k).to_pylist() for k in range(2, 6)), strict=True)) if similarity(*unpack(s, x), *unpack(t, y)) >= threshold]
            if kept:
                yield pa.RecordBatch.from_arrays([batch.column(0).take(pa.array(kept)), batch.column(1).take(pa.array(kept))], schema=schema)

    left = shingles.select(F.col("node").alias("a"), F.col("shingles").alias("s"), F.col("weights").alias("x"))
    right = shingles.select(F.col("node").alias("b"), F.col("shingles").alias("t"), F.col("weights").alias("y"))
    held = pairs.join(left, "a").join(right, "b").select("a", "b", "s", "x", "t", "y")
    return held.mapInArrow(tidied(judge), "a binary, b binary")


def beside(entries: DataFrame, part: list[Column], whole: list[Column], salts: int, keep: str = "true") -> DataFrame:
    """Entries (key, node, ...) with aggregates of their key beside them, of keys that ``keep`` holds for.

    A key that very many nodes have is spread over ``salts`` by node: its parts are summed up
    first, and what comes out goes back to the parts that are there, never to one task.
    """
    salted = entries.withColumn("_s", F.pmod(F.xxhash64("node"), F.lit(salts)).cast("int"))
    parts = salted.groupBy("key", "_s").agg(*part)
    told = parts.groupBy("key").agg(*whole, F.collect_list("_s").alias("_s")).where(keep).withColumn("_s", F.explode("_s"))
    return salted.join(told, ["key", "_s"]).drop("_s")


def _grouped(entries: DataFrame, wide: DataFrame, columns: list[str], block: int, partitions: int) -> DataFrame:
    """Entries (key, node, label) dealt as pairs of blocks: every two members of a bucket meet in one group (key, b1, b2).

    ``wide`` has what else is asked of a node: it joins once buckets are sized, so that only narrow rows are dealt by key.
    """
    sized = beside(entries, [F.count(F.lit(1)).alias("_n")], [F.ceil(F.sum("_n") / block).cast("int").alias("_g")], partitions)
    own = sized.join(wide, "node").withColumn("_b", F.pmod(F.xxhash64("node"), F.col("_g")).cast("int"))
    dealt = own.select("key", *columns, "_b", F.explode(F.sequence(F.lit(0), F.col("_g") - 1)).alias("_o"))
    dealt = dealt.select(F.least("_b", "_o").alias("b1"), F.greatest("_b", "_o").alias("b2"), "key", *columns)
    return dealt.repartition(partitions, "key", "b1", "b2").sortWithinPartitions("key", "b1", "b2")


def _groups(batches):
    """Rows of each group (key, b1, b2) in turn, as lists of columns."""
    held, at = None, None
    for batch in batches:
        for row in zip(*(c.to_pylist() for c in batch.columns), strict=True):
            if row[:3] != at:
                if held:
                    yield held
                held, at = [], row[:3]
            held.append(row[2:])
    if held:
        yield held


def _likely(rows: list, cells_at: int, label_at: int, bands_at: int, bands: int, threshold: float):
    """Index pairs of members of different classes that may be similar and meet in no earlier bucket: blocks of rows."""
    cells = np.stack([np.frombuffer(r[cells_at], np.int32) for r in rows])
    # both kinds of keys of each member; they are the same where it repeats no shingle
    kinds = [np.array([r[bands_at][:bands] for r in rows], np.int64), np.array([r[bands_at][-bands:] for r in rows], np.int64)]
    _, label = np.unique(np.array([r[label_at] for r in rows], dtype="V16"), return_inverse=True)
    key = rows[0][0]
    j = next(int(at[0]) for k in kinds if len(at := np.flatnonzero(k[0] == key)))
    for first in range(0, len(rows), 16):
        part = slice(first, first + 16)
        near = label[part, None] != label[None]
        near &= np.arange(len(rows))[None] > np.arange(first, min(first + 16, len(rows)))[:, None]
        at = np.flatnonzero(near.any(0))
        if not len(at):
            continue
        near[:, at] &= may_reach(cells[part], cells[at], threshold)
        x, y = np.nonzero(near)
        x = x + first
        if j and len(x):
            fresh = np.ones(len(x), bool)
            for k in kinds:
                for m in kinds:
                    fresh &= ~(k[x, :j] == m[y, :j]).any(1)
            x, y = x[fresh], y[fresh]
        yield x, y


def hopeful(entries: DataFrame, wide: DataFrame, threshold: float, bands: int, block: int, partitions: int) -> DataFrame:
    """(key, node): members that may have a partner of another class, judged by cells."""
    schema = pa.schema([("key", pa.int64()), ("node", pa.binary())])

    def judge(batches):
        for rows in _groups(batches):
            marked = np.zeros(len(rows), bool)
            for x, y in _likely(rows, 2, 3, 4, bands, threshold):
                marked[x] = True
                marked[y] = True
            if marked.any():
                nodes = [rows[i][1] for i in np.flatnonzero(marked).tolist()]
                yield pa.RecordBatch.from_arrays([pa.array([rows[0][0]] * len(nodes), pa.int64()), pa.array(nodes, pa.binary())], schema=schema)

    dealt = _grouped(entries, wide, ["node", "cells", "label", "bands"], block, partitions)
    return dealt.select("b1", "b2", "key", "node", "cells", "label", "bands").mapInArrow(tidied(judge), "key long, node binary").distinct()


def settled_links(entries: DataFrame, wide: DataFrame, threshold: float, bands: int, block: int, partitions: int) -> DataFrame:
    """Links (a, b) that join the classes of each group's members, by exact similarity."""
    schema = pa.schema([("a", pa.binary()), ("b", pa.binary())])

    def judge(batches):
        for rows in _groups(batches):
            parent = {r[3]: r[3] for r in rows}

            def root(x):
                while parent[x] != x:
                    parent[x] = parent[parent[x]]
                    x = parent[x]
                return x

            sets = [(np.frombuffer(r[5], np.uint64), np.frombuffer(r[6], np.int32) if r[6] else np.ones(len(r[5]) // 8, np.int32)) for r in rows]
            out = []
            for xs, ys in _likely(rows, 2, 3, 4, bands, threshold):
                for x, y in zip(xs.tolist(), ys.tolist(), strict=True):
                    a, b = root(rows[x][3]), root(rows[y][3])
                    if a != b and similarity(*sets[x], *sets[y]) >= threshold:
                        parent[a] = b
                        out.append((rows[x][1], rows[y][1]))
            if out:
                yield pa.RecordBatch.from_arrays([pa.array(c, pa.binary()) for c in zip(*out, strict=True)], schema=schema)

    dealt = _grouped(entries, wide, ["node", "cells", "label", "bands", "shingles", "weights"], block, partitions)
    return dealt.select("b1", "b2", "key", "node", "cells", "label", "bands", "shingles", "weights").mapInArrow(tidied(judge), "a binary, b binary")


def components(edges: DataFrame, labels: DataFrame | None = None) -> DataFrame:
    """(node, label): the least node reachable over edges (a, b); ``labels`` are known ones to go on from.

    Edges between labels are contracted each round: neighbours' least label, then jumps
    along labels until nothing changes. Tables are written between rounds.
    """
    known = labels
    while True:
        if known is not None:
            edges = edges.join(known.select(F.col("node").alias("a"), F.col("label").alias("_a")), "a", "left").join(known.select(F.col("node").alias("b"), F.col("label").alias("_b")), "b", "left").select(F.coalesce("_a", "a").alias("a"), F.coalesce("_b", "b").alias("b"))
        edges = staged(edges.where("a <> b").select(F.least("a", "b").alias("a"), F.greatest("a", "b").alias("b")).distinct(), "edges")
        if edges.isEmpty():
            return known if known is not None else edges.select(F.col("a").alias("node"), F.col("b").alias("label"))
        # every node points to its least neighbour below it, then to that one's
        both = edges.select(F.col("b").alias("node"), F.col("a").alias("to")).unionByName(edges.select(F.col("a").alias("node"), F.col("a").alias("to")))
        parent = staged(both.groupBy("node").agg(F.min("to").alias("label")), "parents")
        for _ in range(2):
            up = parent.select(F.col("node").alias("label"), F.col("label").alias("_up"))
            parent = staged(parent.join(up, "label", "left").select("node", F.coalesce("_up", "label").alias("label")), "parents")
        if known is None:
            known = parent
        else:
            step = parent.select(F.col("node").alias("label"), F.col("label").alias("_up"))
            moved = known.join(step, "label", "left").select("node", F.coalesce("_up", "label").alias("label"))
            fresh = parent.join(known.select("node"), "node", "left_anti")
            known = staged(moved.unionByName(fresh), "labels")


def near_duplicates(docs: DataFrame, threshold: float = 0.8, size: int = 5, registers: int = 80, bands: int = 20) -> DataFrame:
    """Classes of equal or similar documents (doc_id, text): one row for each input row.

    Returns doc_id, class_id (the least doc_id of the class) and class_size (rows). Two
    texts are linked if their similarity over word shingles (words: runs of letters a-z,
    digits and characters over 127, lower-cased) is ``threshold`` or more, classes are the
    connected parts. A null text is the empty text; texts without words are only linked
    with equal texts; repeated rows are copies; a null doc_id belongs to its text's class
    but never names one unless all ids are null; an empty table gives no rows.
    """
    signed, by_node = _classes(docs, threshold, size, registers, bands)
    return signed.select("doc_id", "node").join(by_node.select("node", "class_id", "class_size"), "node").select("doc_id", "class_id", "class_size")


def keep_first(docs: DataFrame, threshold: float = 0.8, size: int = 5, registers: int = 80, bands: int = 20) -> DataFrame:
    """One document of each class of near-duplicates, with all its columns.

    The row with the least doc_id stays (null ids only where a class has no other), of
    rows with one id the one with the least text digest, of rows equal in both any one.
    """
    signed, by_node = _classes(docs, threshold, size, registers, bands)
    first = by_node.groupBy("class").agg(F.min(F.struct(F.col("doc_id").isNull().alias("none"), "doc_id", "node")).alias("m"))
    id_, node = (free_name(docs.columns, c) for c in ("key", "node"))
    first = first.select(F.coalesce("m.doc_id", F.lit(_NO_ID)).alias(id_), F.col("m.node").alias(node))
    text = F.coalesce(F.col("text"), F.lit(""))
    keyed = docs.withColumn(id_, F.coalesce(F.col("doc_id").cast("long"), F.lit(_NO_ID))).withColumn(node, F.substring(F.unhex(F.sha2(text, 256)), 1, 16))
    kept = keyed.join(first, [id_, node], "left_semi")
    if not _once(signed):
        kept = kept.dropDuplicates([id_, node])
    return kept.select(*docs.columns)


def _once(signed: DataFrame) -> bool:
    """True if no row repeats both the id and the text of another."""
    return signed.groupBy("doc_id", "node").agg(F.count(F.lit(1)).alias("n")).where("n > 1").isEmpty()


def _classes(docs: DataFrame, threshold: float, size: int, registers: int, bands: int) -> tuple[DataFrame, DataFrame]:
    """The signed rows, and (node, doc_id, class, class_id, class_size) of each distinct text."""
    signed = staged(signed_nodes(with_nodes(docs), registers, bands, size), "signed")
    once = _once(signed)
    partitions = shuffle_partitions(docs.sparkSession)
    # one entry for each (bucket, node); copies of a text have equal buckets
    nodes = signed.groupBy("node").agg(F.min("doc_id").alias("doc_id"), F.count(F.lit(1)).alias("rows"), F.first("bands").alias("bands"))
    nodes = staged(nodes, "nodes")
    entries = nodes.select(F.explode(F.array_distinct("bands")).alias("key"), "node")
    open_ = staged(beside(entries, [F.count(F.lit(1)).alias("n")], [F.sum("n").alias("n")], partitions, "n > 1"), "entries")
    labels = None
    if not open_.isEmpty():
        wanted = nodes.join(open_.select("node").distinct(), "node", "left_semi").select("node", F.coalesce("doc_id", F.lit(_NO_ID)).alias("_id"))
        raw = with_nodes(docs).withColumn("_id", F.coalesce("doc_id", F.lit(_NO_ID)))
        shingles = shingle_table(raw.join(wanted, ["_id", "node"]), size)
        # rows that repeat an id and a text would repeat the node
        shingles = staged(shingles if once else shingles.dropDuplicates(["node"]), "shingles")
        degree = open_.groupBy("node").agg(F.sum("n").alias("degree"))
        ranked = open_.select("key", "node").join(degree, "node")
        led = beside(ranked, [F.max(F.struct("degree", "node")).alias("m")], [F.max("m").getField("node").alias("lead")], partitions)
        pairs = led.where("node <> lead").select(F.least("node", "lead").alias("a"), F.greatest("node", "lead").alias("b")).distinct()
        links = staged(verified(pairs, shingles, threshold), "links")
        labels = None if links.isEmpty() else components(links)
        # two members were compared with each other already
        open_ = open_.where("n > 2").select("key", "node")
        open_ = open_.withColumn("label", F.col("node")) if labels is None else open_.join(labels, "node", "left").select("key", "node", F.coalesce("label", "node").alias("label"))
        ends = beside(open_, [F.min("label").alias("_lo"), F.max("label").alias("_hi")], [F.min("_lo").alias("_lo"), F.max("_hi").alias("_hi")], partitions, "_lo <> _hi")
        open_ = staged(ends.select("key", "node", "label"), "entries")
        if not open_.isEmpty():
            wide = shingles.join(nodes.select("node", "bands"), "node")
            some = staged(hopeful(open_, wide.select("node", "cells", "bands"), threshold, bands, 512, partitions), "hopeful")
            if not some.isEmpty():
                links = staged(settled_links(open_.join(some, ["key", "node"]), wide, threshold, bands, 128, partitions), "links")
                if not links.isEmpty():
                    labels = components(links, labels)
    named = nodes.select("node", "doc_id", "rows")
    if labels is None:
        return signed, named.select("node", "doc_id", F.col("node").alias("class"), F.col("doc_id").alias("class_id"), F.col("rows").alias("class_size"))
    named = named.join(labels, "node", "left").withColumn("class", F.coalesce("label", "node"))
    classes = named.groupBy("class").agg(F.min("doc_id").alias("class_id"), F.sum("rows").alias("class_size"))
    return signed, named.select("node", "doc_id", "class").join(classes, "class")
