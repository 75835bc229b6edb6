"""Benchmark decontamination with FM-indexes over training shards.

A shard is what one task reads of the corpus. Its words become numbers of the
benchmark's vocabulary; a word outside it cannot lie in any window, so only runs of
known words that are long enough to hold the shortest window are kept (nothing that
could match is lost). Over these runs the shard builds an FM-index: suffix array by
prefix doubling, Burrows-Wheeler transform, wavelet tree with block ranks, sampled
suffix positions. All windows are searched backward at once, occurrences are located
by walking to sampled positions, and their spans are merged by document. Numbers come
from 64-bit word hashes, so located windows are compared with the text at the end.
"""

from __future__ import annotations

import hashlib
import re

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from .common import blocks_of, free_name, tidied, words_of

#: A word after lower-casing A-Z.
WORD = re.compile("[^\x00-\x2f\x3a-\x60\x7b-\x7f]+")
_LOWER = {i: i + 32 for i in range(65, 91)}

_OUT = pa.schema([("doc_id", pa.int64()), ("n_words", pa.int64()), ("n_hit", pa.int64()), ("n_items", pa.int64()), ("items_sha256", pa.string()), ("contaminated", pa.bool_()), ("items", pa.list_(pa.string())), ("spans", pa.list_(pa.list_(pa.int64())))])
_OUT_DDL = "doc_id long, n_words long, n_hit long, n_items long, items_sha256 string, contaminated boolean, items array<string>, spans array<array<long>>"


def words(text: str | None) -> list[str]:
    return WORD.findall((text or "").translate(_LOWER))


class WaveletTree:
    """Ranks of small integers in a sequence: one bit array for each level, counts at every 64 bits."""

    def __init__(self, values: np.ndarray, bits: int):
        self.bits, self.n = bits, len(values)
        self.words, self.counts, self.zeros = [], [], []
        values = values.astype(np.int64)
        for level in range(bits - 1, -1, -1):
            bit = ((values >> level) & 1).astype(np.uint8)
            packed = np.packbits(np.concatenate([bit, np.zeros(-len(bit) % 64 + 64, np.uint8)]), bitorder="little").view(np.uint64)
            counts = np.zeros(len(packed) + 1, np.int64)
            np.cumsum(np.bitwise_count(packed), out=counts[1:])
            self.words.append(packed)
            self.counts.append(counts)
            self.zeros.append(len(bit) - int(bit.sum()))
            values = np.concatenate([values[bit == 0], values[bit == 1]])  # stable: a wavelet matrix

    def _ones(self, level: int, place: np.ndarray) -> np.ndarray:
        block, rest = place >> 6, (place & 63).astype(np.uint64)
        mask = (np.uint64(1) << rest) - np.uint64(1)
        return self.counts[level][block] + np.bitwise_count(self.words[level][block] & mask).astype(np.int64)

    def rank(self, symbol: np.ndarray, place: np.ndarray) -> np.ndarray:
        """Occurrences of symbol before place, elementwise."""
        start, end = np.zeros(len(place), np.int64), place.astype(np.int64)
        for level in range(self.bits):
            one = ((symbol >> (self.bits - 1 - level)) & 1).astype(bool)
            a, b = self._ones(level, start), self._ones(level, end)
            start = np.where(one, self.zeros[level] + a, start - a)
            end = np.where(one, self.zeros[level] + b, end - b)
        return end - start

    def access(self, place: np.ndarray) -> np.ndarray:
        symbol, at = np.zeros(len(place), np.int64), place.astype(np.int64)
        for level in range(self.bits):
            ones = self._ones(level, at)
            one = self._ones(level, at + 1) > ones
            symbol = (symbol << 1) | one
            at = np.where(one, self.zeros[level] + ones, at - ones)
        return symbol


class FMIndex:
    """Backward search and location over a sequence of numbers >= 1 (0 is the end)."""

    def __init__(self, sequence: np.ndarray, sample: int = 16):
        text = np.concatenate([sequence.astype(np.int64), [0]])
        n = len(text)
        order = np.argsort(text, kind="stable")
        rank = np.empty(n, np.int64)
        rank[order] = np.concatenate([[0], np.cumsum(text[order][1:] != text[order][:-1])])
        step = 1
        while rank.max() < n - 1:
            ahead = np.full(n, -1, np.int64)
            ahead[: n - step] = rank[step:]
            key = rank * (n + 1) + ahead + 1
            order = np.argsort(key, kind="stable")
            rank[order] = np.concatenate([[0], np.cumsum(key[order][1:] != key[order][:-1])])
            step *= 2
        bwt = text[order - 1]
        self.n, top = n, int(text.max()) + 1
        self.first = np.concatenate([[0], np.cumsum(np.bincount(text, minlength=top))])
        self.tree = WaveletTree(bwt, max(1, int(top - 1).bit_length()))
        self.sampled = np.full(n, -1, np.int64)
        kept = order % sample == 0
        self.sampled[kept] = order[kept]
        self.top = top

    def search(self, patterns: np.ndarray) -> tuple[np.ndarray, np.ndarray]:
        """Rows of equal-length patterns to their intervals in the suffix array."""
        low, high = np.zeros(len(patterns), np.int64), np.full(len(patterns), self.n, np.int64)
        for j in range(patterns.shape[1] - 1, -1, -1):
            live = np.flatnonzero((low < high) & (patterns[:, j] < self.top))
            dead = np.setdiff1d(np.arange(len(patterns)), live, assume_unique=True)
            high[dead] = low[dead]
            symbol = patterns[live, j]
            low[live] = self.first[symbol] + self.tree.rank(symbol, low[live])
            high[live] = self.first[symbol] + self.tree.rank(symbol, high[live])
        return low, high

    def locate(self, rows: np.ndarray) -> np.ndarray:
        """Positions of suffix-array rows: each walks back to a sampled one."""
        at, steps, out = rows.copy(), np.zeros(len(rows), np.int64), np.full(len(rows), -1, np.int64)
        left = np.arange(len(rows))
        while len(left):
            found = self.sampled[at[left]] >= 0
            done = left[found]
            out[done] = self.sampled[at[done]] + steps[done]
            left = left[~found]
            symbol = self.tree.access(at[left])
            at[left] = self.first[symbol] + self.tree.rank(symbol, at[left])
            steps[left] += 1
        return out % self.n


class Windows:
    """The benchmark's windows: numbers of a vocabulary, by window length."""

    def __init__(self, items: list[tuple[str, list[str]]], size: int = 10):
        found: dict[tuple[str, ...], set[str]] = {}
        for item, own in items:
            for i in range(max(1, len(own) - size + 1) if own else 0):
                found.setdefault(tuple(own[i : i + size]), set()).add(item)
        self.texts = list(found)
        self.items = [sorted(found[x]) for x in self.texts]
        vocabulary = sorted({w for x in self.texts for w in x})
        raw = "\0".join(vocabulary).encode()
        _, _, hashes, _ = words_of(np.frombuffer(raw, np.uint8), np.array([0, len(raw)])) if raw else (0, 0, np.zeros(0, np.uint64), 0)
        self.hashes, number = np.unique(hashes, return_inverse=True)
        number = dict(zip(vocabulary, (number + 1).tolist(), strict=True))
        self.by_length: dict[int, tuple[np.ndarray, np.ndarray]] = {}
        for length in sorted({len(x) for x in self.texts}):
            own = [i for i, x in enumerate(self.texts) if len(x) == length]
            self.by_length[length] = np.array(own), np.array([[number[w] for w in self.texts[i]] for i in own], np.int64)
        self.shortest = min(self.by_length, default=0)


def _find(windows: Windows, data: np.ndarray, offsets: np.ndarray):
    """Occurrences in one block: (window, first word in the block's word list), and the words."""
    starts, ends, hashes, bounds = words_of(data, offsets)
    at = np.searchsorted(windows.hashes, hashes)
    at[at == len(windows.hashes)] = 0
    known = windows.hashes[at] == hashes if len(windows.hashes) else np.zeros(len(hashes), bool)
    number = np.where(known, at + 1, 0)
    # runs of known words; a document's first word always begins a run
    breaks = np.zeros(len(number) + 1, bool)
    breaks[bounds[bounds < len(breaks)]] = True
    begin = np.flatnonzero(known & (breaks[:-1] | ~np.concatenate([[False], known[:-1]])))
    finish = np.flatnonzero(known & (breaks[1:] | ~np.concatenate([known[1:], [False]]))) + 1
    long = finish - begin >= max(1, windows.shortest)
    begin, finish = begin[long], finish[long]
    if not len(begin):
        return starts, ends, bounds, np.zeros(0, np.int64), np.zeros(0, np.int64)
    # runs joined, each followed by a number that no window holds
    length = finish - begin + 1
    total = np.cumsum(length)
    source = np.repeat(begin - (total - length), length) + np.arange(total[-1])
    sequence = np.empty(total[-1], np.int64)
    stop = np.zeros(total[-1], bool)
    stop[total - 1] = True
    sequence[~stop] = number[source[~stop]]
    sequence[stop] = len(windows.hashes) + 1
    index = FMIndex(sequence)
    which, where = [], []
    for own, patterns in windows.by_length.values():
        low, high = index.search(patterns)
        hit = np.flatnonzero(high > low)
        n = high[hit] - low[hit]
        rows = np.repeat(low[hit] - (np.cumsum(n) - n), n) + np.arange(n.sum())
        which.append(np.repeat(own[hit], n))
        where.append(source[index.locate(rows)])
    return starts, ends, bounds, np.concatenate(which), np.concatenate(where)


def _scan(windows: Windows, batch: pa.RecordBatch, block_bytes: int):
    for first, n_docs, data, offsets in blocks_of(batch, limit=block_bytes):
        starts, ends, bounds, which, where = _find(windows, data, offsets)
        doc = np.searchsorted(bounds, where, "right") - 1
        raw = data.tobytes() if len(which) else b""
        items = [set() for _ in range(n_docs)]
        marks: dict[int, list[tuple[int, int]]] = {}
        order = np.argsort(where, kind="stable")
        for w, p, d in zip(which[order].tolist(), where[order].tolist(), doc[order].tolist(), strict=True):
            own = windows.texts[w]
            if all(raw[starts[p + j] : ends[p + j]].lower() == x.encode() for j, x in enumerate(own)):
                items[d].update(windows.items[w])
                spans = marks.setdefault(d, [])
                p -= int(bounds[d])
                if spans and p <= spans[-1][1]:
                    spans[-1] = (spans[-1][0], max(spans[-1][1], p + len(own)))
                else:
                    spans.append((p, p + len(own)))
        yield first, np.diff(bounds), items, marks


def _windows(benchmark: DataFrame, size: int) -> Windows:
    rows = benchmark.select(F.col("item_id").cast("string"), "text").where(F.col("item_id").isNotNull()).collect()
    return Windows([(r[0], words(r[1])) for r in rows], size)


def benchmark_parts(benchmark: DataFrame, max_mb: float) -> list[DataFrame]:
    """The benchmark, cut by a hash of the items into parts of about max_mb of text if it holds more."""
    held = benchmark.agg(F.coalesce(F.sum(F.octet_length("text")), F.lit(0))).first()[0]
    n = max(1, int(-(-held // (max_mb * (1 << 20)))))
    return [benchmark] if n == 1 else [benchmark.where(F.pmod(F.xxhash64(F.col("item_id").cast("string")), F.lit(n)) == k) for k in range(n)]


def decontaminate(docs: DataFrame, benchmark: DataFrame, size: int = 10, block_bytes: int = 1 << 20, max_benchmark_mb: float = 64) -> DataFrame:
    """Words of documents (doc_id, text) inside occurrences of benchmark (item_id, text) windows.

    Returns doc_id, n_words, n_hit, n_items, items_sha256, contaminated, items (sorted
    as strings) and spans (merged, first and last word exclusive): one row for each
    input row. A null text has no words; an item without words has no window; an item without
    id is nobody's and left out; equal windows of several items count for each; repeated rows are
    judged each; an empty corpus gives no rows, an empty benchmark no hits.

    The benchmark goes to every task, so its size is checked: of more than
    ``max_benchmark_mb`` of text the items are dealt into parts, each searched in a pass of its own, and
    the rows' results are put together: the same rows either way.
    """
    parts = benchmark_parts(benchmark, max_benchmark_mb)
    if len(parts) == 1:
        return _searched(docs.select(F.col("doc_id").cast("long").alias("doc_id"), "text"), _windows(parts[0], size), block_bytes)
    # a row is known by its id and its text; equal rows have equal results and are counted
    keyed = docs.select(F.col("doc_id").cast("long").alias("doc_id"), "text", F.sha2(F.coalesce("text", F.lit("")), 256).alias("node"))
    total = None
    for part in parts:
        found = _searched(keyed, _windows(part, size), block_bytes).select("doc_id", "node", "n_words", "items", "spans")
        total = found if total is None else total.unionByName(found)
    rows = total.groupBy("doc_id", "node").agg(F.first("n_words").alias("n_words"), F.flatten(F.collect_set("items")).alias("items"), F.flatten(F.collect_set("spans")).alias("spans"), (F.count(F.lit(1)) / len(parts)).cast("int").alias("copies"))
    each = rows.select("doc_id", "n_words", "items", "spans", F.explode(F.sequence(F.lit(1), F.col("copies"))).alias("copy"))

    def unite(batches):
        for batch in batches:
            out = []
            for doc, n, items, spans in zip(*(batch.column(i).to_pylist() for i in range(4)), strict=True):
                merged: list[list[int]] = []
                for a, b in sorted(spans):
                    if merged and a <= merged[-1][1]:
                        merged[-1][1] = max(merged[-1][1], b)
                    else:
                        merged.append([a, b])
                own, hit = sorted(set(items)), sum(b - a for a, b in merged)
                out.append((doc, n, hit, len(own), hashlib.sha256(",".join(own).encode()).hexdigest(), hit > 0, own, merged))
            if out:
                yield pa.RecordBatch.from_arrays([pa.array(c, f.type) for c, f in zip(zip(*out, strict=True), _OUT, strict=True)], schema=_OUT)

    return each.drop("copy").mapInArrow(tidied(unite), _OUT_DDL)


def _searched(docs: DataFrame, windows: Windows, block_bytes: int) -> DataFrame:
    """Results of one set of windows for docs (doc_id, text and possibly node, which is kept)."""
    keyed = "node" in docs.columns
    schema = pa.schema([*_OUT, ("node", pa.string())]) if keyed else _OUT

    def scan(batches):
        for batch in batches:
            for first, n_words, items, marks in _scan(windows, batch, block_bytes):
                own = [sorted(x) for x in items]
                spans = [[list(x) for x in marks.get(d, [])] for d in range(len(own))]
                hit = [sum(b - a for a, b in x) for x in spans]
                columns = [batch.column(0).slice(first, len(own)), n_words, hit, [len(x) for x in own], [hashlib.sha256(",".join(x).encode()).hexdigest() for x in own], [n > 0 for n in hit], own, spans]
                if keyed:
                    columns.append(batch.column(2).slice(first, len(own)))
                yield pa.RecordBatch.from_arrays([c if isinstance(c, pa.Array) else pa.array(c, f.type) for c, f in zip(columns, schema, strict=True)], schema=schema)

    return docs.mapInArrow(tidied(scan), _OUT_DDL + (", node string" if keyed else ""))


def cut_passages(docs: DataFrame, benchmark: DataFrame, size: int = 10, block_bytes: int = 1 << 20, max_benchmark_mb: float = 64) -> DataFrame:
    """The same rows and columns with all hit words cut out of the texts (from a span's first word to its last).

    A benchmark of several parts (see :func:`decontaminate`) is searched part by part, and all spans are cut at once.
    """
    parts = benchmark_parts(benchmark, max_benchmark_mb)
    if len(parts) > 1:
        return _cut_in_passes(docs, parts, size, block_bytes)
    windows = _windows(parts[0], size)

    def clean(batches):
        for batch in batches:
            at = batch.schema.get_field_index("text")
            out = batch.column(at).to_pylist()
            for first, _, _, marks in _scan(windows, batch, block_bytes):
                for d, spans in marks.items():
                    out[first + d] = without(out[first + d], spans)
            yield batch.set_column(at, "text", pa.array(out, pa.string()))

    return docs.mapInArrow(tidied(clean), docs.schema)


def without(text: str, spans: list) -> str:
    """The text without the words of spans (first, last exclusive; in order)."""
    place = [m.span() for m in WORD.finditer(text.translate(_LOWER))]
    pieces, end = [], 0
    for a, b in spans:
        pieces.append(text[end : place[a][0]])
        end = place[b - 1][1]
    return "".join([*pieces, text[end:]])


def _cut_in_passes(docs: DataFrame, parts: list[DataFrame], size: int, block_bytes: int) -> DataFrame:
    """Spans of all parts, joined back by id and text, cut together."""
    node, spans = free_name(docs.columns, "node"), free_name(docs.columns, "spans")
    digest = F.sha2(F.coalesce("text", F.lit("")), 256)
    keyed = docs.select(F.col("doc_id").cast("long").alias("doc_id"), "text", digest.alias("node"))
    total = None
    for part in parts:
        one = _searched(keyed, _windows(part, size), block_bytes).where("contaminated").select("node", "spans")
        total = one if total is None else total.unionByName(one)
    # spans depend on the text only
    marks = total.groupBy(F.col("node").alias(node)).agg(F.array_sort(F.flatten(F.collect_set("spans"))).alias(spans))
    joined = docs.withColumn(node, digest).join(marks, node, "left").select(*docs.columns, spans)

    def clean(batches):
        for batch in batches:
            at = batch.schema.get_field_index("text")
            out = batch.column(at).to_pylist()
            for i, found in enumerate(batch.column(batch.num_columns - 1).to_pylist()):
                if found:
                    merged: list[list[int]] = []
                    for a, b in found:
                        if merged and a <= merged[-1][1]:
                            merged[-1][1] = max(merged[-1][1], b)
                        else:
                            merged.append([a, b])
                    out[i] = without(out[i], merged)
            columns = [pa.array(out, pa.string()) if i == at else c for i, c in enumerate(batch.columns[:-1])]
            yield pa.RecordBatch.from_arrays(columns, batch.schema.names[:-1])

    return joined.mapInArrow(tidied(clean), docs.schema)
