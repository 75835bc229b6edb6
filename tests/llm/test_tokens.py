"""Packing and token files: round trips, brute force, odd rows."""

import io
import random
import zlib

import numpy as np
import pytest

from rulegraph.llm.packing import best_pattern, pack, plan_patterns
from rulegraph.llm.queries import vocabulary_path
from rulegraph.llm.token_files import TokenFileReader, TokenFileWriter, read_token_files, token_files, write_token_files
from rulegraph.llm.word_ids import WordIds


@pytest.fixture(scope="module")
def library():
    from tokenizers import Tokenizer

    return Tokenizer.from_file(vocabulary_path())


def test_ids_equal_the_librarys(library):
    rnd = random.Random(1)
    wide = "abcXYZéÀÿßµªº'sdtrevml0129²¼ \t\n\r.,;<|>endoftext\x0b\x0c\x85\xa0\x1cİKſ中文αΣς́"
    plain = "abcXYZéÀÿßµªº'sdtrevmlSTVLD0129²¼ \t\n\r.,;<>÷×¡"
    texts = ["".join(rnd.choice(a) for _ in range(rnd.randint(0, 60))) for a in (wide, plain) for _ in range(800)]
    texts += ["", "<|endoftext|>", "a<|startoftext|>b", "a'stb", "x'LL d'", "don't we'RE", " ", "\n"]
    coder = WordIds(vocabulary_path(), cache_words=200)
    for i in range(0, len(texts), 100):
        ids, bounds = coder.encode(texts[i : i + 100], 2)
        for j, text in enumerate(texts[i : i + 100]):
            assert ids[bounds[j] : bounds[j + 1]].tolist() == [*library.encode(text, add_special_tokens=False).ids, 2], text


ROWS = [(5, "one two three"), (1, None), (2, ""), (7, "x"), (7, "x"), (None, "no id"), (9, "word " * 9000), (3, "naïve café")]


def frame(spark, rows=ROWS):
    return spark.createDataFrame([(*r, "a", 1) for r in rows], "doc_id long, text string, part string, rank int")


def test_token_files_round_trip(spark, library):
    got = sorted(token_files(frame(spark), vocabulary_path(), frame_ids=64).collect(), key=lambda r: r["start"])
    ids = [r["doc_id"] for r in got]
    assert ids == [None, 1, 2, 3, 5, 7, 7, 9]
    texts = {r[0]: r[1] or "" for r in ROWS}
    start = 0
    for r in got:
        want = np.array([*library.encode(texts[r["doc_id"]], add_special_tokens=False).ids, 2], "<u4")
        assert (r["start"], r["n_tokens"], r["ids_crc32"]) == (start, len(want), zlib.crc32(want.tobytes()))
        start += len(want)


def test_reader_reads_only_what_is_asked_and_checks_it():
    class Sink(io.BytesIO):
        def close(self):
            pass

    class Source(io.BytesIO):
        def size(self):
            return len(self.getbuffer())

    sink = Sink()
    writer = TokenFileWriter(sink, frame_ids=10)
    docs = [np.arange(n, dtype=np.uint32) + n for n in (3, 0, 25, 1, 40)]
    bounds = np.concatenate([[0], np.cumsum([len(d) for d in docs])])
    writer.add(np.arange(5), np.concatenate(docs), bounds)
    writer.close()
    reader = TokenFileReader(Source(sink.getvalue()))
    for i in (4, 0, 2, 1, 3):
        assert reader.read(i).tolist() == docs[i].tolist()
    reader.frames_read = 0
    reader.read(0)
    assert reader.frames_read == 1
    assert [c for _, c in reader.checksums()] == [zlib.crc32(d.astype("<u4").tobytes()) for d in docs]
    broken = bytearray(sink.getvalue())
    reader.checks = reader.checks.copy()
    reader.checks[0] ^= 1
    with pytest.raises(ValueError):
        reader.read(0)
    with pytest.raises(ValueError):
        TokenFileReader(Source(bytes(broken[:-1]) + b"x"))


def test_empty_tables(spark):
    empty = frame(spark, []).where("false")
    assert token_files(empty, vocabulary_path()).count() == 0
    assert pack(empty, vocabulary_path()).count() == 0


def test_manifest_is_one_row_a_file(spark, tmp_path):
    manifest = write_token_files(frame(spark), f"file://{tmp_path}/t", vocabulary_path())
    assert sum(r["n_docs"] for r in manifest) == len(ROWS)
    assert read_token_files(spark, f"file://{tmp_path}/t", manifest).count() == len(ROWS)


def test_packing_keeps_each_id_once(spark, library):
    got = pack(frame(spark), vocabulary_path()).toPandas()
    texts = {r[0]: r[1] or "" for r in ROWS}
    assert got["length"].sum() == sum(len(library.encode(r[1] or "", add_special_tokens=False).ids) + 1 for r in ROWS)
    for doc, own in got[got.doc_id.notna()].groupby("doc_id"):
        ids = np.array([*library.encode(texts[int(doc)], add_special_tokens=False).ids, 2], "<u4")
        for r in own.itertuples():
            assert r.doc_tokens == len(ids)
            assert r.ids_crc32 == zlib.crc32(ids[r.start : r.start + r.length].tobytes())
    for _, own in got.groupby("sequence_id"):
        own = own.sort_values("offset")
        assert own["offset"].tolist() == [0, *own["length"].cumsum().tolist()[:-1]]
        assert own["length"].sum() <= 4096
    assert sorted(got.sequence_id.unique()) == list(range(got.sequence_id.nunique()))


def test_packing_pads_little(spark, sf_dir):
    got = pack(spark.read.parquet(f"{sf_dir}/documents.parquet"), vocabulary_path()).groupBy("sequence_id").sum("length").toPandas()
    assert got["sum(length)"].sum() / (4096 * len(got)) > 0.95


def test_knapsack_against_all_patterns():
    rng = np.random.default_rng(0)
    for _ in range(20):
        sizes = np.sort(rng.choice(np.arange(1, 12), 4, replace=False))
        values = rng.random(4)
        best, pattern = best_pattern(values, sizes, 12)
        ranges = [range(12 // s + 1) for s in sizes]
        want = max(sum(v * n for v, n in zip(values, ns, strict=True)) for ns in np.ndindex(*[len(r) for r in ranges]) if sum(s * n for s, n in zip(sizes, ns, strict=True)) <= 12)
        assert best == pytest.approx(want)
        assert (pattern * sizes).sum() <= 12
        assert (pattern * values).sum() == pytest.approx(want)


def test_patterns_meet_demand_near_the_bound():
    rng = np.random.default_rng(1)
    demand = {int(s): int(n) for s, n in zip(range(1, 65), rng.integers(0, 500, 64), strict=True)}
    plan = plan_patterns(demand, 64)
    made: dict[int, int] = {}
    for pattern, times in plan:
        assert sum(s * n for s, n in pattern.items()) <= 64
        for s, n in pattern.items():
            made[s] = made.get(s, 0) + n * times
    assert made == {s: n for s, n in demand.items() if n}
    assert sum(t for _, t in plan) <= 1.03 * sum(s * n for s, n in demand.items()) / 64 + len(demand)
    assert plan_patterns({}, 64) == []
