"""Sharding, substrings, decontamination, near-duplicates, secrets, language: brute force and odd rows."""

import hashlib
import itertools
import random
import re
import zlib
from collections import Counter

import numpy as np
import pytest
from pyspark.sql import functions as F

from rulegraph.llm import decontaminate as de
from rulegraph.llm import language as la
from rulegraph.llm import neardup as nd
from rulegraph.llm import secrets as se
from rulegraph.llm import sharding as sh
from rulegraph.llm import substrings as su
from rulegraph.llm.common import blocks_of, mix64, words_of


def frame(spark, rows):
    return spark.createDataFrame([(*r, "x", 1, True) for r in rows], "doc_id long, text string, node string, rank int, copy boolean")


def documents(spark, sf_dir):
    return spark.read.parquet(f"{sf_dir}/documents.parquet")


# ---- words ------------------------------------------------------------------------------------------------


def test_words_never_cross_documents():
    raw = ["ab", "cd é", "", "1a", "-"]
    data = np.frombuffer("".join(raw).encode(), np.uint8)
    offsets = np.concatenate([[0], np.cumsum([len(x.encode()) for x in raw])])
    starts, ends, hashes, bounds = words_of(data, offsets)
    assert [data[a:b].tobytes().decode() for a, b in zip(starts, ends, strict=True)] == ["ab", "cd", "é", "1a"]
    assert bounds.tolist() == [0, 1, 3, 3, 4, 4]
    _, _, again, _ = words_of(np.frombuffer(b"AB xx CD", np.uint8), np.array([0, 8]))
    assert again[0] == hashes[0] and again[2] == hashes[1]


# ---- sharding -----------------------------------------------------------------------------------------------


def check_shards(got, rows, shards=8):
    counts = Counter(r["shard"] for r in got)
    assert len(got) == len(rows)
    sizes = [counts.get(s, 0) for s in range(shards)]
    assert max(sizes) - min(sizes) <= 1
    for s in range(shards):
        assert sorted(r["slot"] for r in got if r["shard"] == s) == list(range(sizes[s]))
    want = Counter((d, len((t or "").encode()) + 1, zlib.crc32((t or "").encode())) for d, t in rows)
    assert Counter((r["doc_id"], r["size"], r["text_crc32"]) for r in got) == want


def test_shards_are_even_and_keep_copies_together(spark):
    rows = [(i, f"t{i}") for i in range(200)] + [(300 + i, f"copy {i % 10}") for i in range(60)] + [(None, None), (7, ""), (8, "t8"), (8, "t8")]
    got = sh.shard_rows(frame(spark, rows)).collect()
    check_shards(got, rows)
    of = {r["doc_id"]: r["shard"] for r in got if r["doc_id"] and r["doc_id"] >= 300}
    split = sum(len({of[300 + i] for i in range(60) if i % 10 == k}) > 1 for k in range(10))
    assert split <= 2


@pytest.mark.parametrize("alone", [0, 50])
def test_groups_are_whole_where_nearly_all_rows_are_linked(spark, alone):
    sizes = [2] * 200 + [5] * 60 + [20] * 15
    rows = [(i, f"copy {g}") for i, g in enumerate(g for g, n in enumerate(sizes) for _ in range(n))]
    rows += [(5000 + i, f"alone {i}") for i in range(alone)]
    got = sh.shard_rows(frame(spark, rows)).collect()
    check_shards(got, rows)
    text = dict(rows)
    seen = {}
    for r in got:
        seen.setdefault(text[r["doc_id"]], set()).add(r["shard"])
    # each of the eight shards may be left with one row, too little for a group of two
    assert sum(len(x) > 1 for x in seen.values()) <= 4


def test_cut_links_are_counted(spark):
    docs = frame(spark, [(i, f"copy {i // 2}") for i in range(40)] + [(100 + i, "many") for i in range(30)])
    found = sh.shard_rows(docs, 8)
    report = sh.cut_links(found).first()
    assert report["n_groups"] == 21 and report["n_links"] == 20 + 29
    assert 30 - 9 <= report["n_cut_links"] <= 30  # a group of 30 needs four shards of eight or nine
    assert sh.cut_links(sh.shard_rows(docs.where("false"), 8)).first()["n_cut_links"] == 0


def test_a_group_of_a_third_fills_whole_shards(spark):
    rows = [(i, "same" if i % 3 == 0 else f"t{i}") for i in range(480)]
    got = sh.shard_rows(frame(spark, rows)).collect()
    check_shards(got, rows)
    held = Counter(r["shard"] for r in got if r["doc_id"] % 3 == 0)
    assert sum(n for _, n in held.most_common(3)) >= 150


@pytest.mark.parametrize("n", [0, 1, 5])
def test_few_rows(spark, n):
    rows = [(i, "t") for i in range(n)]
    check_shards(sh.shard_rows(frame(spark, rows)).collect(), rows)


# ---- substrings -----------------------------------------------------------------------------------------------


def removed_by_force(rows, length=50):
    first = {}
    order = lambda d: -1e18 if d is None else d
    for d, t in rows:
        b = (t or "").encode()
        for i in range(len(b) - length + 1):
            first[b[i : i + length]] = min(first.get(b[i : i + length], 1e19), order(d))
    out = []
    for d, t in rows:
        b = (t or "").encode()
        mask = np.zeros(len(b), bool)
        for i in range(len(b) - length + 1):
            if first[b[i : i + length]] < order(d):
                mask[i : i + length] = True
        kept = bytes(x for x, m in zip(b, mask, strict=True) if not m)
        spans = int((np.diff(np.concatenate([[0], mask.astype(int)])) == 1).sum())
        out.append((d, len(b), int(mask.sum()), spans, hashlib.sha256(kept).hexdigest()))
    return sorted(out, key=repr)


@pytest.mark.parametrize("crowded", [3.0, 0.05])
def test_removed_bytes_against_brute_force(spark, crowded):
    rnd = random.Random(2)
    base = ["".join(rnd.choice("abcdé ") for _ in range(rnd.randint(40, 140))) for _ in range(12)] + ["a" * 300, "ab" * 100]
    rows = []
    for i in range(150):
        parts = [rnd.choice([rnd.choice(base), "".join(rnd.choice("abcdefgh ") for _ in range(rnd.randint(0, 60)))]) for _ in range(rnd.randint(0, 5))]
        rows.append((rnd.choice([i, i, i, rnd.randint(0, 150)]), "".join(parts)))
    rows += rows[:10] + [(None, rows[5][1]), (None, None), (7, None), (400, ""), (None, base[0])] + [(500 + i, rows[3][1]) for i in range(5)]
    got = su.removed_bytes(frame(spark, rows), crowded=crowded).collect()
    assert sorted((tuple(r)[:5] for r in got), key=repr) == removed_by_force(rows)


def test_removed_bytes_of_documents(spark, sf_dir):
    docs = documents(spark, sf_dir)
    got = su.removed_bytes(docs).collect()
    assert sorted((tuple(r)[:5] for r in got), key=repr) == removed_by_force([tuple(r) for r in docs.select("doc_id", "text").collect()])
    assert su.removed_bytes(docs.where("false")).count() == 0


def test_bands_see_pairs_just_over_the_threshold():
    """Hundreds of made pairs of similarity 0.8 to 0.9: all share a band (one in 37,600 at 0.8 may not)."""
    rnd = np.random.default_rng(5)
    texts = []
    for _ in range(2000):
        own = rnd.integers(0, 50_000, int(rnd.integers(60, 200)))
        other = own.copy()
        changed = max(1, int(len(own) * rnd.uniform(0.005, 0.045)))
        other[rnd.choice(len(own), changed, replace=False)] = rnd.integers(50_000, 99_999, changed)
        texts += [" ".join(f"w{x}" for x in own).encode(), " ".join(f"w{x}" for x in other).encode()]
    shingles, weights, bounds = nd.shingles_of(np.frombuffer(b"".join(texts), np.uint8), np.concatenate([[0], np.cumsum([len(x) for x in texts])]))
    bands = nd.all_bands(shingles, weights, bounds, 80, 20)
    part = lambda i: (shingles[bounds[i] : bounds[i + 1]], weights[bounds[i] : bounds[i + 1]])
    near = [i for i in range(0, len(texts), 2) if 0.8 <= nd.similarity(*part(i), *part(i + 1)) < 0.9]
    assert len(near) > 500
    assert all(set(bands[i]) & set(bands[i + 1]) for i in near)


def test_suffix_array_and_prefixes():
    rng = np.random.default_rng(0)
    for _ in range(20):
        text = rng.integers(97, 99, rng.integers(1, 300)).astype(np.uint8)
        order = su.suffix_array(text, 50)
        raw = text.tobytes() + bytes(200)
        keys = [raw[i : i + 50] for i in order]
        assert keys == sorted(keys) and sorted(order.tolist()) == list(range(len(text)))
        common = su.common_prefixes(text, order, 50)
        for k in range(1, len(order)):
            a, b = keys[k - 1], keys[k]
            assert common[k] == next((i for i in range(50) if a[i] != b[i]), 50)


def test_merge_by_binary_search():
    rng = np.random.default_rng(3)
    windows = rng.integers(0, 3, (300, 50)).astype(np.uint8)
    windows[:, 5:] = 0
    owners = rng.integers(0, 1000, 300)
    least = {}
    for w, o in zip(windows, owners, strict=True):
        least[w.tobytes()] = min(o, least.get(w.tobytes(), 9999))
    assert su.merge_windows(windows, owners).tolist() == [least[w.tobytes()] for w in windows]


# ---- decontamination --------------------------------------------------------------------------------------------


def hits_by_force(docs, items, size=10):
    windows = {}
    for item, text in items:
        own = de.words(text)
        for i in range(max(1, len(own) - size + 1) if own else 0):
            windows.setdefault(tuple(own[i : i + size]), set()).add(str(item))
    out = []
    for doc, text in docs:
        own, hit, found = de.words(text), set(), set()
        for n in {len(w) for w in windows}:
            for i in range(len(own) - n + 1):
                if tuple(own[i : i + n]) in windows:
                    hit |= set(range(i, i + n))
                    found |= windows[tuple(own[i : i + n])]
        out.append((doc, len(own), len(hit), len(found), hashlib.sha256(",".join(sorted(found)).encode()).hexdigest(), bool(hit)))
    return sorted(out, key=repr)


def test_hits_against_brute_force(spark):
    rnd = random.Random(4)
    vocabulary = ["A", "b", "CÉ", "d1", "e"]
    text = lambda n: rnd.choice([" ", "-", ". "]).join(rnd.choice(vocabulary) for _ in range(n))
    items = [(i, text(rnd.choice([0, 1, 3, 9, 10, 11, 14]))) for i in range(12)] + [(99, None), (10, "a b")]
    docs = [(i, text(rnd.randint(0, 60))) for i in range(60)] + [(None, items[3][1]), (1, None), (2, ""), (3, items[5][1] + " x")]
    bench = spark.createDataFrame(items, "item_id long, text string")
    got = de.decontaminate(frame(spark, docs), bench, block_bytes=200).collect()
    assert sorted((tuple(r)[:6] for r in got), key=repr) == hits_by_force(docs, items)
    none = de.decontaminate(frame(spark, docs), bench.where("false")).collect()
    assert not any(r["contaminated"] for r in none)
    assert de.decontaminate(frame(spark, docs).where("false"), bench).count() == 0
    # a benchmark too large for one pass is searched in parts, with the same rows
    assert len(de.benchmark_parts(bench, 4e-5)) > 2
    again = de.decontaminate(frame(spark, docs), bench, block_bytes=200, max_benchmark_mb=4e-5).collect()
    assert sorted(map(tuple, again), key=repr) == sorted(map(tuple, got), key=repr)
    clashing = frame(spark, docs).selectExpr("*", "1 AS spans", "2 AS _spans", "3 AS _node")
    one, many = ([tuple(r) for r in de.cut_passages(clashing, bench, max_benchmark_mb=mb).collect()] for mb in (64, 4e-5))
    assert sorted(one, key=repr) == sorted(many, key=repr)


def test_passages_are_cut_and_the_rest_stays(spark):
    passage = " ".join(f"w{i}" for i in range(12))
    docs = frame(spark, [(1, f"before {passage} after"), (2, "clean text"), (3, None)])
    got = {r["doc_id"]: r["text"] for r in de.cut_passages(docs, spark.createDataFrame([(0, passage)], "item_id long, text string")).collect()}
    assert got == {1: "before  after", 2: "clean text", 3: None}


def test_fm_index_ranks_and_locations():
    rng = np.random.default_rng(5)
    text = rng.integers(1, 7, 500)
    index = de.FMIndex(text, sample=7)
    patterns = rng.integers(1, 8, (50, 3))
    low, high = index.search(patterns)
    for p, a, b in zip(patterns, low, high, strict=True):
        want = [i for i in range(498) if (text[i : i + 3] == p).all()]
        assert sorted(index.locate(np.arange(a, b)).tolist()) == want


# ---- near-duplicates ----------------------------------------------------------------------------------------------


def test_similarity_and_estimate():
    rng = np.random.default_rng(6)
    for _ in range(50):
        a = {int(x): int(rng.integers(1, 4)) for x in rng.choice(60, rng.integers(1, 40), replace=False)}
        b = {int(x): int(rng.integers(1, 4)) for x in rng.choice(60, rng.integers(1, 40), replace=False)}
        both, either = a.keys() & b.keys(), a.keys() | b.keys()
        plain = len(both) / len(either)
        probability = sum(1 / sum(max(a.get(k, 0) / a[i], b.get(k, 0) / b[i]) for k in either) for i in both)
        packed = lambda c: (np.array(sorted(c), np.uint64), np.array([c[x] for x in sorted(c)]))
        assert nd.similarity(*packed(a), *packed(b)) == pytest.approx(max(plain, probability))
    mixed = lambda c: (mix64(np.array(sorted(c), np.uint64)), np.array([c[x] for x in sorted(c)]))
    (x, wx), (y, wy) = mixed(a), mixed(b)
    signed = nd.signatures(np.concatenate([x, y]), np.concatenate([wx, wy]), np.array([0, len(x), len(x) + len(y)]), 4096)
    assert (signed[0] == signed[1]).mean() == pytest.approx(probability, abs=0.03)


def classes_by_force(docs, threshold=0.8, size=5):
    sets = []
    for _, t in docs:
        w = de.words(t)
        sets.append(Counter(tuple(w[i : i + size]) for i in range(max(1, len(w) - size + 1))) if w else Counter())
    parent = list(range(len(docs)))

    def root(x):
        while parent[x] != x:
            x = parent[x]
        return x

    for i, j in itertools.combinations(range(len(docs)), 2):
        a, b = sets[i], sets[j]
        same = (docs[i][1] or "") == (docs[j][1] or "")
        if not same and (a.keys() & b.keys()):
            either = a.keys() | b.keys()
            s = len(a.keys() & b.keys()) / len(either)
            if s >= 0.5:
                s = max(s, sum(1 / sum(max(a.get(k, 0) / a[i2], b.get(k, 0) / b[i2]) for k in either) for i2 in a.keys() & b.keys()))
            same = s >= threshold
        if same:
            parent[root(j)] = root(i)
    return [root(i) for i in range(len(docs))]


def test_classes_against_brute_force(spark, sf_dir):
    docs = [(r["doc_id"], r["text"]) for r in documents(spark, sf_dir).select("doc_id", "text").collect()]
    rnd = random.Random(7)
    long = [w for w in de.words(docs[0][1] + docs[1][1])][:200]
    for i in range(30):  # a family of near copies around one text, with different distances
        own = list(long)
        for _ in range(rnd.choice([0, 1, 2, 4, 8])):
            own[rnd.randrange(len(own))] = f"new{rnd.random()}"
        docs.append((10_000 + i, " ".join(own)))
    docs += [(20_000, None), (20_001, ""), (20_002, "- -"), (20_003, "one two"), (20_004, "One TWO")]
    got = {r["doc_id"]: r["class_id"] for r in nd.near_duplicates(frame(spark, docs)).collect()}
    roots = classes_by_force(docs)
    want = {}
    for (d, _), r in zip(docs, roots, strict=True):
        want.setdefault(r, []).append(d)
    assert {d: min(group) for group in want.values() for d in group} == got


def test_plain_similarity_of_texts_that_repeat_lines(spark):
    docs = []
    for f in range(60):  # equal sets of shingles, a tenth of them thirty times as often in one text
        lines = [f"a{f} b{f} c{f} d{f} l{i}" for i in range(2)]
        body = " ".join(f"w{f}x{i}" for i in range(90))
        docs += [(100 * f + k, " ".join(lines * n) + " " + body) for k, n in enumerate((2, 60))]
    got = {r["doc_id"]: r["class_id"] for r in nd.near_duplicates(frame(spark, docs)).collect()}
    assert got == {100 * f + k: 100 * f for f in range(60) for k in range(2)}


def test_a_crowded_key_is_told_by_parts(spark):
    rows = [(k, i.to_bytes(2, "big")) for k, n in ((1, 400), (2, 2), (3, 1)) for i in range(n)]
    got = nd.beside(spark.createDataFrame(rows, "key long, node binary"), [F.count(F.lit(1)).alias("n"), F.max("node").alias("top")], [F.sum("n").alias("n"), F.max("top").alias("top")], 7, "n > 1").collect()
    assert sorted((r.key, bytes(r.node), r.n, bytes(r.top)) for r in got) == sorted((k, x, n, (n - 1).to_bytes(2, "big")) for k, n in ((1, 400), (2, 2)) for q, x in rows if q == k)


def test_cells_never_reject_a_pair_at_the_threshold():
    rng = np.random.default_rng(3)
    pool = mix64(np.arange(400, dtype=np.uint64))
    sets = []
    for _ in range(60):
        own = np.sort(rng.choice(pool[: rng.integers(20, 400)], 18, replace=False))
        sets.append((own, rng.integers(1, 4, len(own))))
        drop = np.delete(own, rng.integers(len(own)))
        sets.append((drop, rng.integers(1, 9, len(drop))))
    cells = np.stack([nd.cells_of(*x) for x in sets])
    for threshold in (0.3, 0.5, 0.8, 0.9):
        may = nd.may_reach(cells, cells, threshold)
        exact = np.array([[nd.similarity(*x, *y) >= threshold for y in sets] for x in sets])
        assert may[exact].all() and not may.all()


def test_repeated_rows_null_ids_and_empty_tables(spark):
    text = "a b c d e f g h"
    rows = [(1, text), (1, text), (None, text), (None, "other words in here now"), (2, "x"), (2, "y")]
    got = nd.near_duplicates(frame(spark, rows)).collect()
    assert Counter((r["doc_id"], r["class_id"], r["class_size"]) for r in got) == Counter([(1, 1, 3), (1, 1, 3), (None, 1, 3), (None, None, 1), (2, 2, 1), (2, 2, 1)])
    kept = nd.keep_first(frame(spark, rows)).collect()
    assert Counter((r["doc_id"], r["text"]) for r in kept) == Counter([(1, text), (None, "other words in here now"), (2, "x"), (2, "y")])
    assert kept[0]["node"] == "x" and kept[0]["rank"] == 1
    assert nd.near_duplicates(frame(spark, rows).where("false")).count() == 0


# ---- secrets ------------------------------------------------------------------------------------------------------

_ASSIGN = re.compile(r"""(?i:(password|passwd|secret|token|api_?key))["']?\x20*[:=]\x20*["']?([A-Za-z0-9+/_.=-]+)""", re.A)


def base_spans(t):
    out = [("assign", m.start(), m.end()) for m in _ASSIGN.finditer(t) if len(m[2]) >= 12]
    out += [("access", m.start(), m.end()) for m in re.finditer("AKIA[A-Z0-9]+", t) if len(m[0]) >= 18]
    out += [("hex", m.start(), m.end()) for m in re.finditer("[0-9a-f]+", t) if len(m[0]) >= 16]
    return sorted(out, key=lambda x: (x[1], ("assign", "access", "hex").index(x[0])))


def test_base_secrets_equal_the_plain_expressions():
    rnd = random.Random(3)
    parts = ["password", "PassWd", "token", "API_KEY", "apikey", "=", ":", " ", "'", '"', "abcdef0123456789", "AKIA", "ABCDEFGH12345678", "é", "中", "K", "toKen", "ghp_", "x" * 30, "a" * 16, "secret"]
    for _ in range(4000):
        text = "".join(rnd.choice(parts) for _ in range(rnd.randint(0, 12)))
        assert [x for x in se.find(text) if x[0] in se.KINDS[:3]] == base_spans(text), text


def test_checksums_decide(spark):
    body = "Zx" * 15
    good = f"ghp_{body}{se.checksum_62(body)}"
    assert ("checked", 3, 43) in se.find(f"é: {good} ")
    assert not se.find(f"ghp_{body}{'0' * 6}")
    assert se.redact(f"key {good}.") == "key [checked]."
    docs = frame(spark, [(1, good), (2, None), (None, ""), (1, good)])
    got = se.scan_secrets(docs).collect()
    assert sorted((str(r["doc_id"]), r["spans"]) for r in got) == [("1", "checked:0:40"), ("1", "checked:0:40"), ("2", ""), ("None", "")]
    masked = {r["doc_id"]: r["text"] for r in se.redact_column(docs).collect()}
    assert masked == {1: "[checked]", 2: None, None: ""}
    assert se.scan_secrets(docs.where("false")).count() == 0


# ---- language -----------------------------------------------------------------------------------------------------


def test_forward_backward_against_all_paths():
    rng = np.random.default_rng(1)
    score, step = rng.normal(size=(7, 3)), rng.normal(size=(3, 3))
    first, length = np.array([0, 4]), np.array([4, 3])
    got, pairs, log_z = la.forward_backward(score, first, length, step)
    want, want_pairs, want_z = np.zeros((7, 3)), np.zeros((3, 3)), 0.0
    for f, n in zip(first, length, strict=True):
        total, own, moves = 0.0, np.zeros((n, 3)), np.zeros((3, 3))
        for path in itertools.product(range(3), repeat=int(n)):
            w = np.exp(sum(score[f + i, path[i]] for i in range(n)) + sum(step[path[i - 1], path[i]] for i in range(1, n)))
            total += w
            for i in range(n):
                own[i, path[i]] += w
            for i in range(1, n):
                moves[path[i - 1], path[i]] += w
        want[f : f + n], want_z = own / total, want_z + np.log(total)
        want_pairs += moves / total
    assert np.allclose(got, want) and np.allclose(pairs, want_pairs) and np.isclose(log_z, want_z)


def test_runs_of_a_text_are_one_chain():
    rng = np.random.default_rng(3)
    score, step = rng.normal(size=(400, 3)), rng.normal(size=(3, 3))
    bounds = np.array([0, 0, 7, 207, 208, 400])
    whole = la.forward_backward(score, *la.chains_of(bounds, 1000), step)[0]
    for chain in (1, 3, 64):
        assert np.allclose(la.forward_backward(score, *la.chains_of(bounds, chain), step, bounds)[0], whole)


def test_held_out_accuracy_and_code_switching(spark, sf_dir):
    docs = documents(spark, sf_dir)
    model = la.fit(docs)
    got = la.identify(docs, model).toPandas().merge(docs.select("doc_id", "lang").toPandas(), on="doc_id")
    test = got[got.held_out]
    assert len(test) and (test.lang_pred == test.lang).mean() >= 0.95
    assert all(r == (zlib.crc32(str(d).encode()) % 4 == 2) for d, r in zip(got.doc_id, got.held_out, strict=True))
    texts = docs.where("lang in ('de', 'en') and length(text) > 600").orderBy("doc_id").limit(30).toPandas()
    a, b = (texts[texts.lang == x].text.iloc[0][:400] for x in ("de", "en"))
    raw = np.frombuffer((a + " " + b).encode(), np.uint8)
    offsets = np.array([0, len(raw)])
    words = words_of(raw, offsets)
    labels = np.array(model.labels)[model.words(raw, *words).argmax(1)]
    half = len(de.words(a))
    assert (labels[: half - 5] == "de").mean() > 0.8 and (labels[half + 5 :] == "en").mean() > 0.8


def test_all_labels_and_all_of_a_text_are_learned(spark):
    held = lambda d: zlib.crc32(str(d).encode()) % 4 == 2
    rows = [(d, f"word{d % 70} text", f"l{d % 70}") for d in range(400) if not held(d)]
    model = la.fit(spark.createDataFrame(rows, "doc_id long, text string, lang string"), buckets=256, steps=1)
    assert model.labels == sorted({x for _, _, x in rows}) and len(model.labels) == 70
    runs = la.spread_runs(10, 5010, 400, 64)
    assert runs[0][0] == 10 and runs[-1][-1] == 5009 and sum(map(len, runs)) == 400
    assert np.concatenate(la.spread_runs(3, 303, 400, 64)).tolist() == list(range(3, 303))
    long = spark.createDataFrame([("a" * 50 + "b" * 50,), ("short",)], "text string")
    assert [r[0] for r in long.select(la.excerpt(16)).collect()] == [" ".join(["aa"] * 4 + ["bb"] * 4), "short"]


def test_texts_without_letters_and_models_without_labels(spark):
    model = la.train(["der die das und", "the and of to"], ["de", "en"])
    rows = [(1, None), (2, ""), (3, "123 --"), (4, "—"), (5, "the and"), (None, "der"), (5, "the and")]
    got = sorted(((str(r["doc_id"]), r["lang_pred"], r["score"] > 0) for r in la.identify(frame(spark, rows), model).collect()))
    assert got == [("1", "und", False), ("2", "und", False), ("3", "und", False), ("4", "und", False), ("5", "en", True), ("5", "en", True), ("None", "de", True)]
    empty = la.train([], [])
    assert {r["lang_pred"] for r in la.identify(frame(spark, rows), empty).collect()} == {"und"}
    assert la.identify(frame(spark, rows).where("false"), model).count() == 0
    both = la.with_language(frame(spark, rows), model, "_l", "_s")
    assert both.columns == ["doc_id", "text", "node", "rank", "copy", "_l", "_s"] and both.count() == len(rows)


def test_blocks_hold_every_text():
    import pyarrow as pa

    batch = pa.RecordBatch.from_arrays([pa.array([None, "ab", "", "cde", "f" * 50])], ["text"]).slice(1)
    seen = [(first, n, bytes(data), offsets.tolist()) for first, n, data, offsets in blocks_of(batch, limit=4)]
    assert sum(n for _, n, _, _ in seen) == 4
    assert b"".join(x[2] for x in seen) == b"abcde" + b"f" * 50
