"""Removal of repeated byte strings with suffix arrays.

A byte goes if a string of ``length`` bytes that covers it also starts in a document
with a smaller id. The plan, from cheap to dear:

1. Equal texts: only the one with the least id is looked at; the others go whole.
2. Anchors: every window of ``length`` bytes has a key, the least hash of the k-byte
   grams inside. Equal windows have equal keys, and neighbouring windows mostly share
   one, so a text becomes runs of windows with one key. Only keys that occur in two
   different texts can hold repeats; tasks exchange packed (key, run) entries to find
   them. What one task already knows to be shared it sends once, so a passage found in
   many documents makes few entries.
3. Shards: runs with shared keys are cut out of the texts and dealt by key, so windows
   that are equal meet in one shard. A shard builds a suffix array over its runs by
   Larsson-Sadakane refinement, takes common prefixes of neighbours in Kasai's sense
   (cut at ``length``), and finds each window's least document.
4. A bucket of keys with far more runs than others is dealt over several shards. Each
   settles what it can and sends on the windows of its least owners only, which are
   merged by binary search in sorted tables.
5. Removed byte ranges are merged by document and cut out of the text.
"""

from __future__ import annotations

import hashlib

import numpy as np
import pyarrow as pa
import xxhash
from pyspark import TaskContext
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from .common import blocks_of, mix64, shuffle_partitions, staged, tidied

_NO_ID = -(1 << 63)
_ENTRY = np.dtype([("hash", "<u4"), ("node", "<i8"), ("start", "<u4"), ("count", "u1")])
_SHARED = np.dtype([("node", "<i8"), ("start", "<u4"), ("count", "u1"), ("bucket", "<u4"), ("hash", "<u4")])
_RUN = np.dtype([("doc", "<i8"), ("node", "<i8"), ("start", "<u4"), ("count", "u1"), ("hash", "<u4")])
_MARK = np.dtype([("doc", "<i8"), ("node", "<i8"), ("first", "<u4"), ("last", "<u4")])
_MAX_RUN = 200
#: Parts of a bucket that are settled one after the other (by the low bits of the key), so that a suffix array stays small.
_FINE = 8


def _grams(data: np.ndarray) -> np.ndarray:
    """At each place the eight bytes from there as one number (zeros after the end)."""
    v = np.zeros(len(data) + 8, np.uint64)
    v[: len(data)] = data
    for step, shift in ((1, 8), (2, 16), (4, 32)):
        v[:-step] |= v[step:] << np.uint64(shift)
    return v[: len(data)]


def window_runs(data: np.ndarray, offsets: np.ndarray, length: int = 50, gram: int = 16) -> tuple[np.ndarray, np.ndarray, np.ndarray, np.ndarray]:
    """Runs of windows with one key: text, first byte in the block, number of windows, key."""
    n = len(data)
    if n < length:
        return (np.zeros(0, np.int64),) * 3 + (np.zeros(0, np.uint64),)
    v = _grams(data)
    h = v[: n - gram + 1] * np.uint64(0x9E3779B97F4A7C15)
    h ^= h >> np.uint64(29)
    h += v[gram - 8 : n - 8 + 1]
    h *= np.uint64(0xBF58476D1CE4E5B9)
    h ^= h >> np.uint64(32)
    h *= np.uint64(0x94D049BB133111EB)
    least, held, width = h, 1, length - gram + 1
    while held * 2 <= width:
        least = np.minimum(least[:-held], least[held:])
        held *= 2
    if width > held:
        least = np.minimum(least[: len(least) - (width - held)], least[width - held :])
    windows = n - length + 1
    size = np.diff(offsets)
    valid = np.zeros(n + 1, np.int64)
    long = size >= length
    np.add.at(valid, offsets[:-1][long], 1)
    np.add.at(valid, offsets[1:][long] - length + 1, -1)
    valid = np.cumsum(valid)[:windows] > 0
    new = np.empty(windows, bool)
    new[0] = True
    np.not_equal(least[1:], least[:-1], out=new[1:])
    new[1:] |= valid[1:] != valid[:-1]
    starts = offsets[:-1][long]
    new[starts[starts < windows]] = True
    first = np.flatnonzero(new)
    count = np.diff(np.concatenate([first, [windows]]))
    keep = valid[first]
    first, count = first[keep], count[keep]
    if (count > _MAX_RUN).any():
        parts = -(-count // _MAX_RUN)
        nth = np.arange(parts.sum()) - np.repeat(np.cumsum(parts) - parts, parts)
        count = np.minimum(_MAX_RUN, np.repeat(count, parts) - nth * _MAX_RUN)
        first = np.repeat(first, parts) + nth * _MAX_RUN
    return np.searchsorted(offsets, first, "right") - 1, first, count, mix64(least[first])


def suffix_array(text: np.ndarray, depth: int) -> np.ndarray:
    """Suffixes ordered by their first ``depth`` bytes at least (zeros after the end).

    Larsson-Sadakane: sorted by eight bytes first; then groups of more than one suffix
    are refined by the rank of what follows, the compared length doubling each time.
    """
    n = len(text)
    key = _grams(text).byteswap()
    order = np.argsort(key)
    ordered = key[order]
    new = np.concatenate([[True], ordered[1:] != ordered[:-1]]) if n else np.zeros(0, bool)
    starts = np.flatnonzero(new)
    rank = np.full(n + depth + 64, -1, np.int64)
    rank[order] = np.repeat(starts, np.diff(np.concatenate([starts, [n]])))
    step = 8
    while step < depth:
        size = np.diff(np.concatenate([starts, [n]]))
        open_ = np.repeat(size > 1, size)
        place = np.flatnonzero(open_)
        if not len(place):
            break
        own = order[place]
        group, ahead = rank[own], rank[own + step]
        sub = np.argsort(group * (n + 1) + ahead)  # both are below n
        own, group, ahead = own[sub], group[sub], ahead[sub]
        order[place] = own
        fresh = np.concatenate([[True], (group[1:] != group[:-1]) | (ahead[1:] != ahead[:-1])])
        at = np.flatnonzero(fresh)
        changed = np.repeat(place[at], np.diff(np.concatenate([at, [len(place)]])))
        rank[own] = changed
        mark = np.zeros(n, bool)
        mark[starts] = True
        mark[place[at]] = True
        starts = np.flatnonzero(mark)
        step *= 2
    return order


def common_prefixes(text: np.ndarray, order: np.ndarray, limit: int) -> np.ndarray:
    """Common prefix of each suffix with the one before it in order, cut at ``limit``.

    The values of Kasai's algorithm; all pairs advance eight bytes at a time together.
    """
    v = np.concatenate([_grams(text), np.zeros(limit + 8, np.uint64)])
    out = np.zeros(len(order), np.int64)
    live = np.arange(1, len(order))
    for step in range(0, limit, 8):
        if not len(live):
            break
        differs = v[order[live] + step] ^ v[order[live - 1] + step]
        same = differs == 0
        low = differs[~same] & (~differs[~same] + np.uint64(1))
        out[live[~same]] += np.bitwise_count(low - np.uint64(1)).astype(np.int64) // 8
        out[live[same]] += 8
        live = live[same]
    return np.minimum(out, limit)


def least_owners(bodies: list[bytes], counts: np.ndarray, owners: np.ndarray, length: int) -> tuple[np.ndarray, np.ndarray, np.ndarray, np.ndarray]:
    """For each window of the runs: run, place in it, least owner among equal windows here, group of equal windows."""
    text = np.frombuffer(b"".join(bodies), np.uint8)
    begin = np.concatenate([[0], np.cumsum(counts + length - 1)])
    run = np.repeat(np.arange(len(bodies)), counts)
    place = np.arange(len(run)) - np.repeat(np.cumsum(counts) - counts, counts)
    at = begin[run] + place
    window = np.full(len(text), -1, np.int64)
    window[at] = np.arange(len(run))
    order = suffix_array(text, length)
    order = order[window[order] >= 0]
    group = np.cumsum(common_prefixes(text, order, length) < length) - 1
    member = window[order]
    least = np.full(int(group[-1]) + 1 if len(group) else 0, np.iinfo(np.int64).max)
    np.minimum.at(least, group, owners[run[member]])
    by_window = np.empty(len(run), np.int64)
    by_window[member] = group
    return run, place, least[by_window], by_window


def merge_windows(windows: np.ndarray, owners: np.ndarray) -> np.ndarray:
    """Least owner of each window (rows of bytes) over all shards: sorted table and binary search."""
    table = _sorted_unique(windows)
    at = _search_rows(table, windows)
    least = np.full(len(table), np.iinfo(np.int64).max)
    np.minimum.at(least, at, owners)
    return least[at]


def _columns(rows: np.ndarray) -> list[np.ndarray]:
    padded = np.zeros((len(rows), -(-rows.shape[1] // 8) * 8), np.uint8)
    padded[:, : rows.shape[1]] = rows
    words = padded.view(">u8").astype(np.uint64)
    return [words[:, i] for i in range(words.shape[1])]


def _sorted_unique(rows: np.ndarray) -> np.ndarray:
    columns = _columns(rows)
    order = np.lexsort(columns[::-1])
    new = np.zeros(len(rows), bool)
    new[:1] = True
    for c in columns:
        new[1:] |= c[order][1:] != c[order][:-1]
    return rows[order[new]]


def _search_rows(table: np.ndarray, rows: np.ndarray) -> np.ndarray:
    """Binary search of all rows in the sorted table at once."""
    have, want = _columns(table), _columns(rows)
    low, high = np.zeros(len(rows), np.int64), np.full(len(rows), len(table), np.int64)
    while True:
        live = np.flatnonzero(low < high)
        if not len(live):
            return low
        mid = (low[live] + high[live]) // 2
        less, equal = np.zeros(len(live), bool), np.ones(len(live), bool)
        for h, w in zip(have, want, strict=True):
            a, b = h[mid], w[live]
            less |= equal & (a < b)
            equal &= a == b
        low[live[less]] = mid[less] + 1
        high[live[~less]] = mid[~less]


def _entries(docs: DataFrame, length: int, gram: int, buckets: int, flush_bytes: int) -> DataFrame:
    """Packed entries by bucket of the key, and (bucket drawn, kind 1) what is known to be shared already."""
    schema = pa.schema([("bucket", pa.int32()), ("kind", pa.int32()), ("packed", pa.binary())])

    def scan(batches):
        held, bytes_held, seen = [], 0, set()

        def flush():
            node, start, count, key = (np.concatenate(x) for x in zip(*held, strict=True))
            held.clear()
            order = np.argsort(key)
            node, start, count, key = node[order], start[order], count[order], key[order]
            new = np.concatenate([[True], key[1:] != key[:-1]])
            group = np.cumsum(new) - 1
            first = np.flatnonzero(new)
            known = (np.minimum.reduceat(node, first) != np.maximum.reduceat(node, first))[group]
            shared = np.empty(int(known.sum()), _SHARED)
            bucket = ((key >> np.uint64(32)) % np.uint64(buckets)).astype(np.int64)
            for name, value in (("node", node), ("start", start), ("count", count), ("bucket", bucket), ("hash", key & np.uint64(0xFFFFFFFF))):
                shared[name] = value[known]
            # one entry stands for a key that is shared here: node 0, and how many it stands for
            send = ~known | new
            start = np.where(known, np.bincount(group)[group], start)
            bucket = bucket[send]
            packed = np.empty(int(send.sum()), _ENTRY)
            packed["hash"] = key[send] & np.uint64(0xFFFFFFFF)
            packed["node"] = np.where(known[send], 0, node[send])
            packed["start"], packed["count"] = start[send], count[send]
            by = np.argsort(bucket)
            packed, bounds = packed[by], np.searchsorted(bucket[by], np.arange(buckets + 1))
            rows = [(b, 0, packed[bounds[b] : bounds[b + 1]].tobytes()) for b in range(buckets) if bounds[b + 1] > bounds[b]]
            piece = 1 << 16
            rows += [(int(mix64(np.array([i + len(rows)], np.uint64))[0] % np.uint64(buckets)), 1, shared[i : i + piece].tobytes()) for i in range(0, len(shared), piece)]
            return pa.RecordBatch.from_arrays([pa.array(c, f.type) for c, f in zip(zip(*rows, strict=True), schema, strict=True)], schema=schema)

        for batch in batches:
            for _, n, data, offsets in blocks_of(batch):
                raw = memoryview(np.ascontiguousarray(data)).cast("B")
                nodes = np.array([xxhash.xxh64_intdigest(raw[a:b], 42) for a, b in zip(offsets[:-1].tolist(), offsets[1:].tolist(), strict=True)], np.uint64).view(np.int64)
                text, first, count, key = window_runs(data, offsets, length, gram)
                fresh = np.array([x not in seen and not seen.add(x) for x in nodes.tolist()], bool)
                keep = fresh[text]
                text, first, count, key = text[keep], first[keep], count[keep], key[keep]
                if len(text):
                    held.append((nodes[text], (first - offsets[text]).astype(np.uint32), count.astype(np.uint8), key))
                bytes_held += len(data)
                if bytes_held >= flush_bytes and held:
                    yield flush()
                    bytes_held = 0
                    seen.clear()
        if held:
            yield flush()

    return docs.mapInArrow(tidied(scan), "bucket int, kind int, packed binary")


def _shared_runs(entries: DataFrame, partitions: int) -> DataFrame:
    """(node, place, key): runs whose key occurs in two different texts, place being start * 256 + count.

    One row without node for each bucket gives the number of its shared runs.
    """
    schema = pa.schema([("node", pa.int64()), ("place", pa.int64()), ("key", pa.int64())])

    def pack(x, bucket, hashes):
        place = x["start"].astype(np.int64) * 256 + x["count"]
        return pa.RecordBatch.from_arrays([pa.array(x["node"].astype(np.int64)), pa.array(place), pa.array((bucket << 32) | hashes.astype(np.int64))], schema=schema)

    def meet(batches):
        buckets: dict[int, list[bytes]] = {}
        for batch in batches:
            for bucket, kind, packed in zip(*(batch.column(i).to_pylist() for i in range(3)), strict=True):
                if kind == 1:
                    x = np.frombuffer(packed, _SHARED)
                    yield pack(x, x["bucket"].astype(np.int64), x["hash"])
                else:
                    buckets.setdefault(bucket, []).append(packed)
        for bucket in sorted(buckets):
            x = np.frombuffer(b"".join(buckets.pop(bucket)), _ENTRY)
            order = np.argsort(x["hash"])
            h, node = x["hash"][order], x["node"][order]
            new = np.concatenate([[True], h[1:] != h[:-1]])
            group = np.cumsum(new) - 1
            first = np.flatnonzero(new)
            # shared: two different nodes, or an entry that stands for a shared key
            stands = node == 0
            many = (np.minimum.reduceat(node, first) != np.maximum.reduceat(node, first)) | np.logical_or.reduceat(stands, first)
            keep = many[group] & ~stands
            total = int(keep.sum()) + int(x["start"][order[stands]].sum())
            yield pa.RecordBatch.from_arrays([pa.array([None], pa.int64()), pa.array([total]), pa.array([bucket])], schema=schema)
            if keep.any():
                own = x[order[keep]]
                yield pack(own, np.int64(bucket), own["hash"])

    return entries.repartition(partitions, "bucket").mapInArrow(tidied(meet), "node long, place long, key long")


def _marks_by_bucket(marks: np.ndarray, buckets: int):
    """(bucket of the node, packed marks)."""
    bucket = (mix64(marks["node"].view(np.uint64)) % np.uint64(buckets)).astype(np.int64)
    order = np.argsort(bucket)
    marks, bounds = marks[order], np.searchsorted(bucket[order], np.arange(buckets + 1))
    for b in range(buckets):
        if bounds[b + 1] > bounds[b]:
            yield b, marks[bounds[b] : bounds[b + 1]].tobytes()


_CUT = pa.schema([("bucket", pa.int32()), ("salt", pa.int32()), ("kind", pa.int32()), ("packed", pa.binary()), ("bodies", pa.binary())])
_CUT_DDL = "bucket int, salt int, kind int, packed binary, bodies binary"


def _cut_runs(texts: DataFrame, length: int, splits: np.ndarray, flush_bytes: int) -> DataFrame:
    """Runs cut out of texts (doc_id, node, text, runs), packed by shard (bucket, salt): kind 0.

    Equal runs of one flush are sent once, with their least document; the others are
    known to lose the whole run: kind 1, packed marks by bucket of the node.
    """
    buckets = len(splits)

    def cut(batches):
        part = TaskContext.get().partitionId()
        runs, bodies, size, flushes = [], [], 0, 0

        def flush():
            x = np.concatenate([r[0] for r in runs])
            bucket = np.concatenate([r[1] for r in runs])
            docs = x["doc"].tolist()
            best: dict[bytes, int] = {}
            for i, body in enumerate(bodies):
                j = best.get(body)
                if j is None or docs[i] < docs[j]:
                    best[body] = i
            keep = x["doc"] == x["doc"][np.fromiter((best[b] for b in bodies), np.int64, len(bodies))]
            rows = []
            lost = x[~keep]
            if len(lost):
                marks = np.empty(len(lost), _MARK)
                marks["doc"], marks["node"], marks["first"] = lost["doc"], lost["node"], lost["start"]
                marks["last"] = lost["start"] + lost["count"] + (length - 1)
                rows += [(b, 0, 1, packed, None) for b, packed in _marks_by_bucket(marks, buckets)]
            own = np.flatnonzero(keep)
            own = own[np.argsort(bucket[own], kind="stable")]
            bounds = np.searchsorted(bucket[own], np.arange(buckets + 1))
            turn = part * 7 + flushes
            for b in range(buckets):
                mine = own[bounds[b] : bounds[b + 1]]
                if len(mine):
                    rows.append((b, turn % int(splits[b]), 0, x[mine].tobytes(), b"".join([bodies[i] for i in mine.tolist()])))
            return pa.RecordBatch.from_arrays([pa.array(c, f.type) for c, f in zip(zip(*rows, strict=True), _CUT, strict=True)], schema=_CUT)

        for batch in batches:
            ids, nodes, texts, found = (batch.column(i) for i in range(4))
            for doc, node, text, own in zip(ids.to_pylist(), nodes.to_pylist(), texts, found, strict=True):
                raw = text.as_py().encode()
                place, key = (c.to_numpy() for c in own.values.flatten())
                place, one = np.unique(place, return_index=True)
                key = key[one]
                x = np.empty(len(place), _RUN)
                x["doc"], x["node"], x["start"], x["count"], x["hash"] = doc, node, place >> 8, place & 255, key & 0xFFFFFFFF
                runs.append((x, key >> 32))
                bodies += [raw[a >> 8 : (a >> 8) + (a & 255) + length - 1] for a in place.tolist()]
                size += int((place & 255).sum()) + (length + 60) * len(place)
                if size >= flush_bytes:
                    yield flush()
                    runs, bodies, size, flushes = [], [], 0, flushes + 1
        if runs:
            yield flush()

    return texts.select("doc_id", "node", "text", "runs").mapInArrow(tidied(cut), _CUT_DDL)


_SETTLED = pa.schema([("bucket", pa.int32()), ("marks", pa.binary()), ("windows", pa.binary())])
_SETTLED_DDL = "bucket int, marks binary, windows binary"


def _window(length: int) -> np.dtype:
    return np.dtype([("bytes", "u1", (length,)), ("doc", "<i8"), ("node", "<i8"), ("start", "<u4")])


def _windows_by_bucket(windows: np.ndarray, buckets: int):
    """(bucket of the window's bytes, packed windows)."""
    total = np.zeros(len(windows), np.uint64)
    for c in _columns(windows["bytes"]):
        total = mix64(total ^ c)
    bucket = (total % np.uint64(buckets)).astype(np.int64)
    order = np.argsort(bucket)
    windows, bounds = windows[order], np.searchsorted(bucket[order], np.arange(buckets + 1))
    for b in range(buckets):
        if bounds[b + 1] > bounds[b]:
            yield b, windows[bounds[b] : bounds[b + 1]].tobytes()


def _shards(cut: DataFrame, length: int, splits: np.ndarray, partitions: int) -> DataFrame:
    """Settles each shard: packed marks by bucket of the node, and packed windows of split shards that go on."""
    buckets = len(splits)

    def one(x: np.ndarray, raw: bytes, split: bool):
        size = x["count"].astype(np.int64) + (length - 1)
        at = np.concatenate([[0], np.cumsum(size)])
        number: dict[bytes, int] = {}
        body = np.fromiter((number.setdefault(raw[a:b], len(number)) for a, b in zip(at[:-1].tolist(), at[1:].tolist(), strict=True)), np.int64, len(x))
        distinct = list(number)
        owner = np.full(len(distinct), np.iinfo(np.int64).max)
        np.minimum.at(owner, body, x["doc"])
        key = np.empty(len(distinct), np.uint32)
        key[body] = x["hash"]
        _, which, times = np.unique(key, return_inverse=True, return_counts=True)
        several = np.flatnonzero(times[which] > 1)  # a key with one run holds no other equal window
        spans: dict[int, list[int]] = {}
        lost_at: dict[int, np.ndarray] = {}
        if len(several):
            counts = np.array([len(distinct[i]) - length + 1 for i in several.tolist()])
            run, place, least, _ = least_owners([distinct[i] for i in several.tolist()], counts, owner[several], length)
            lost = np.flatnonzero(least < owner[several][run])
            bounds = np.searchsorted(run[lost], np.arange(len(several) + 1))
            for i in np.unique(run[lost]).tolist():
                places = place[lost[bounds[i] : bounds[i + 1]]]
                spans[int(several[i])] = _spans(places, length)
                lost_at[int(several[i])] = places
        whole = x["doc"] > owner[body]
        marks = np.empty(int(whole.sum()), _MARK)
        marks["doc"], marks["node"], marks["first"] = x["doc"][whole], x["node"][whole], x["start"][whole]
        marks["last"] = x["start"][whole] + size[whole]
        partly = np.flatnonzero(~whole & np.isin(body, np.fromiter(spans, np.int64, len(spans))))
        more = [(x["doc"][i], x["node"][i], int(x["start"][i]) + a, int(x["start"][i]) + b) for i in partly.tolist() for a, b in zip(spans[int(body[i])][::2], spans[int(body[i])][1::2], strict=True)]
        marks = np.concatenate([marks, np.array(more, _MARK)]) if more else marks
        parts = []
        if split:
            data = np.frombuffer(raw, np.uint8)
            for i in np.flatnonzero(~whole).tolist():
                places = np.setdiff1d(np.arange(int(x["count"][i])), lost_at.get(int(body[i]), np.zeros(0, np.int64)), assume_unique=True)
                own = np.empty(len(places), _window(length))
                own["bytes"] = np.lib.stride_tricks.sliding_window_view(data[at[i] : at[i + 1]], length)[places]
                own["doc"], own["node"], own["start"] = x["doc"][i], x["node"][i], int(x["start"][i]) + places
                parts.append(own)
        return marks, parts

    def settle(batches):
        held, at, marks, windows, size = [], None, [], [], 0

        def flush():
            x = np.concatenate([np.frombuffer(p, _RUN) for p, _ in held])
            raw = b"".join(b for _, b in held)
            ends = np.cumsum(x["count"].astype(np.int64) + (length - 1))
            begins = ends - (x["count"].astype(np.int64) + (length - 1))
            total = 0
            for part in range(_FINE):
                mine = np.flatnonzero(x["hash"] % _FINE == part)
                if len(mine):
                    own, more = one(x[mine], b"".join([raw[a:b] for a, b in zip(begins[mine].tolist(), ends[mine].tolist(), strict=True)]), splits[at[0]] > 1)
                    marks.append(own)
                    windows.extend(more)
                    total += own.nbytes + sum(w.nbytes for w in more)
            held.clear()
            return total

        def pack():
            rows = [(b, packed, None) for b, packed in _marks_by_bucket(np.concatenate(marks), buckets)] if marks else []
            rows += [(b, None, packed) for b, packed in _windows_by_bucket(np.concatenate(windows), buckets)] if windows else []
            marks.clear()
            windows.clear()
            if rows:
                yield pa.RecordBatch.from_arrays([pa.array(c, f.type) for c, f in zip(zip(*rows, strict=True), _SETTLED, strict=True)], schema=_SETTLED)

        for batch in batches:
            for bucket, salt, kind, packed, bodies in zip(*(c.to_pylist() for c in batch.columns), strict=True):
                if kind == 1:
                    marks.append(np.frombuffer(packed, _MARK))
                    size += len(packed)
                    continue
                if (bucket, salt) != at:
                    size += flush() if held else 0
                    at = (bucket, salt)
                held.append((packed, bodies))
            if size > 32 << 20:
                yield from pack()
                size = 0
        if held:
            flush()
        yield from pack()

    return cut.repartition(partitions, "bucket", "salt").sortWithinPartitions("bucket", "salt").mapInArrow(tidied(settle), _SETTLED_DDL)


def _merge(settled: DataFrame, length: int, buckets: int, partitions: int) -> DataFrame:
    """Windows of split shards against each other: packed marks of those that a smaller document holds."""
    schema = pa.schema([("bucket", pa.int32()), ("marks", pa.binary())])

    def merge(batches):
        held, at = [], None

        def flush():
            x = np.frombuffer(b"".join(held), _window(length))
            lost = x[merge_windows(np.ascontiguousarray(x["bytes"]), x["doc"]) < x["doc"]]
            marks = np.empty(len(lost), _MARK)
            marks["doc"], marks["node"], marks["first"], marks["last"] = lost["doc"], lost["node"], lost["start"], lost["start"] + length
            return list(_marks_by_bucket(marks, buckets))

        def pack(rows):
            return pa.RecordBatch.from_arrays([pa.array(c, f.type) for c, f in zip(zip(*rows, strict=True), schema, strict=True)], schema=schema)

        for batch in batches:
            for bucket, packed in zip(batch.column(0).to_pylist(), batch.column(1).to_pylist(), strict=True):
                if bucket != at:
                    if held and (rows := flush()):
                        yield pack(rows)
                    held, at = [], bucket
                held.append(packed)
        if held and (rows := flush()):
            yield pack(rows)

    asked = settled.where(F.col("windows").isNotNull()).select("bucket", "windows").repartition(partitions, "bucket").sortWithinPartitions("bucket")
    return asked.mapInArrow(tidied(merge), "bucket int, marks binary")


def _united(marks: DataFrame, partitions: int) -> DataFrame:
    """(doc_id, node, marks): removed byte ranges of each text, sorted and merged."""
    schema = pa.schema([("doc_id", pa.int64()), ("node", pa.int64()), ("marks", pa.list_(pa.int64()))])

    def unite(batches):
        held: list[bytes] = []
        at = None

        def flush():
            x = np.frombuffer(b"".join(held), _MARK)
            x = x[np.lexsort((x["first"], x["node"], x["doc"]))]
            new = np.concatenate([[True], (x["doc"][1:] != x["doc"][:-1]) | (x["node"][1:] != x["node"][:-1])])
            text = np.cumsum(new) - 1
            first, last = x["first"].astype(np.int64), x["last"].astype(np.int64)
            shift = text.astype(np.int64) << 33  # texts apart, so that one running maximum serves all
            reach = np.maximum.accumulate(last + shift)
            begin = np.concatenate([[True], first[1:] + shift[1:] > reach[:-1]])
            starts = np.flatnonzero(begin)
            ends = np.concatenate([starts[1:] - 1, [len(x) - 1]])
            flat = np.stack([first[starts], reach[ends] - shift[ends]], 1).ravel()
            head = np.flatnonzero(new)
            bounds = 2 * np.searchsorted(starts, np.concatenate([head, [len(x)]]))
            return pa.RecordBatch.from_arrays([pa.array(x["doc"][head]), pa.array(x["node"][head]), pa.ListArray.from_arrays(pa.array(bounds.astype(np.int32)), pa.array(flat))], schema=schema)

        for batch in batches:
            for bucket, packed in zip(batch.column(0).to_pylist(), batch.column(1).to_pylist(), strict=True):
                if bucket != at:
                    if held:
                        yield flush()
                    held, at = [], bucket
                held.append(packed)
        if held:
            yield flush()

    return marks.repartition(partitions, "bucket").sortWithinPartitions("bucket").mapInArrow(tidied(unite), "doc_id long, node long, marks array<long>")


def _spans(places: np.ndarray, length: int) -> list[int]:
    """Bytes covered by windows at sorted places, as a flat list of bounds."""
    cut = np.flatnonzero(np.diff(places) > length)
    first, last = places[np.concatenate([[0], cut + 1])], places[np.concatenate([cut, [len(places) - 1]])] + length
    return np.stack([first, last], 1).ravel().tolist()


#: More buckets would cut what a task sends at a time into crumbs; beyond 8 TB of texts a task holds more instead.
_MOST_TASKS = 1 << 16


def removed_bytes(docs: DataFrame, length: int = 50, gram: int = 16, crowded: float = 3.0, flush_bytes: int = 16 << 20, task_bytes: int = 128 << 20) -> DataFrame:
    """Bytes of each document (doc_id, text) covered by a ``length``-byte string that starts in a smaller document.

    Returns doc_id, n_bytes, n_removed, n_spans, kept_sha256, spans (removed byte ranges): one row for
    each input row. A null text is empty; a null doc_id is smaller than all others; rows
    with one doc_id do not count as smaller than each other; texts under ``length`` bytes
    keep everything; an empty table gives no rows. A bucket of keys with over ``crowded``
    times the mean number of shared runs is split over several shards. There is a task for about
    every ``task_bytes`` of text, and at least one for each shuffle partition.
    """
    spark = docs.sparkSession
    base = docs.select(F.coalesce(F.col("doc_id").cast("long"), F.lit(_NO_ID)).alias("doc_id"), F.coalesce("text", F.lit("")).alias("text")).withColumn("node", F.xxhash64("text"))
    index = staged(base.select("doc_id", "node", F.unhex(F.sha2("text", 256)).alias("digest"), F.octet_length("text").alias("size")), "index")
    # tasks and buckets grow with the texts, so that what one of them holds does not
    held = index.agg(F.coalesce(F.sum("size"), F.lit(0))).first()[0]
    partitions = min(max(shuffle_partitions(spark), -(-held // task_bytes)), _MOST_TASKS)
    buckets = 2 * partitions
    index = index.drop("size")
    nodes = staged(index.groupBy("node", "digest").agg(F.min("doc_id").alias("first")), "nodes")
    shared = staged(_shared_runs(_entries(base.select("text"), length, gram, buckets, flush_bytes), partitions), "shared")
    totals = np.zeros(buckets, np.int64)  # one number for each bucket: bounded by the number of partitions
    for r in shared.where(F.col("node").isNull()).select("key", "place").collect():
        totals[r["key"]] += r["place"]
    splits = np.maximum(1, np.ceil(totals / max(1.0, crowded * totals.mean()))).astype(np.int64)
    packed = shared.where(F.col("node").isNotNull()).groupBy("node").agg(F.collect_list(F.struct("place", "key")).alias("runs"))
    wanted = staged(packed.join(nodes.select("node", F.col("first").alias("doc_id")), "node"), "wanted")
    cut = _cut_runs(base.join(wanted, ["doc_id", "node"]).select("doc_id", "node", "text", "runs"), length, splits, flush_bytes)
    settled = staged(_shards(cut, length, splits, partitions), "settled")
    marks = settled.where(F.col("marks").isNotNull()).select("bucket", "marks").unionByName(_merge(settled, length, buckets, partitions))
    marks = staged(_united(marks, partitions), "marks")
    copies = index.join(nodes, ["node", "digest"]).where("doc_id > first").select("doc_id", "node").distinct().withColumn("copy", F.lit(True))
    lost = marks.join(copies, ["doc_id", "node"], "full")
    return _finish(base.join(lost, ["doc_id", "node"], "left"), length)


def _finish(joined: DataFrame, length: int) -> DataFrame:
    schema = pa.schema([("doc_id", pa.int64()), ("n_bytes", pa.int64()), ("n_removed", pa.int64()), ("n_spans", pa.int64()), ("kept_sha256", pa.string()), ("spans", pa.list_(pa.int64()))])

    def finish(batches):
        for batch in batches:
            out = []
            for doc, text, marks, copy in zip(*(batch.column(i).to_pylist() for i in range(4)), strict=True):
                raw = text.encode()
                if copy and len(raw) >= length:
                    spans = [0, len(raw)]
                else:
                    spans = marks or []
                kept, at = hashlib.sha256(), 0
                for a, b in zip(spans[::2], spans[1::2], strict=True):
                    kept.update(raw[at:a])
                    at = b
                kept.update(raw[at:])
                out.append((None if doc == _NO_ID else doc, len(raw), sum(spans[1::2]) - sum(spans[::2]), len(spans) // 2, kept.hexdigest(), spans))
            if out:
                yield pa.RecordBatch.from_arrays([pa.array(c, f.type) for c, f in zip(zip(*out, strict=True), schema, strict=True)], schema=schema)

    return joined.select("doc_id", "text", "marks", "copy").mapInArrow(tidied(finish), "doc_id long, n_bytes long, n_removed long, n_spans long, kept_sha256 string, spans array<long>")
