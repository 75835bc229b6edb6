"""Chat formatting, exact search and the pipeline."""

import hashlib
import random

import numpy as np
import pytest

from rulegraph.llm import chat as ch
from rulegraph.llm.search import PivotTable, top_k

PARTS = ["<s>", "</s>", "[INST]", "[/INST]", "<<SYS>>", "<</SYS>>", "<", "\\", "[", "a", "/", "s>", "INST]", "\n", "é"]


def test_templates_read_back_whatever_texts_say():
    rnd = random.Random(5)
    for _ in range(3000):
        messages = [(rnd.choice(["user", "assistant", "system", "tool", "", "[ROLE]"]), "".join(rnd.choice(PARTS) for _ in range(rnd.randint(0, 6)))) for _ in range(rnd.randint(1, 9))]
        shown, spans, mask = ch.turn_spans(messages, ch.instruct_template, window=3)
        assert shown == ch.instruct_template(messages) and ch.instruct_parse(shown) == messages and len(spans) == len(messages)
        loss = "".join(ch.unescape(shown[a:b]) for a, b in mask)
        assert loss == "".join(t for r, t in messages if r == "assistant")


def test_rewritten_history_is_found(spark):
    def counting(messages):
        return f"{len(messages)} turns: " + "|".join(t for _, t in messages)

    def not_local(messages):
        return "".join(f"{i}{t}|" for i, (_, t) in enumerate(messages))

    with pytest.raises(ch.HistoryRewritten):
        ch.turn_spans([("user", "a"), ("user", "b")], counting)
    many = [("user", str(i)) for i in range(40)]
    shown, spans, _ = ch.turn_spans(many, not_local, window=4)
    assert shown == not_local(many) and spans[-1][1] == len(shown)
    rows = spark.createDataFrame([(1, 0, "user", "a"), (1, 1, "assistant", "b")], "conv_id long, turn long, role string, text string")
    assert ch.format_chats(rows, counting).first()["rewritten"]


def test_masks_need_no_knowledge_of_the_template():
    shown, _, mask = ch.turn_spans([("user", "s"), ("assistant", "s"), ("assistant", "a\\b"), ("assistant", "")], lambda m: "".join(f"[{r}]{t}" for r, t in m))
    assert [shown[a:b] for a, b in mask] == ["s", "a\\b", ""] and shown[mask[0][0] - 1] == "]"
    shown, _, mask = ch.turn_spans([("assistant", "ab"), ("user", "x"), ("assistant", "<i>")], lambda m: "".join(f"<{t.upper()}></{r}>" for r, t in m))
    assert [shown[a:b] for a, b in mask] == ["AB", "<I>"]
    many = [("assistant", str(i % 3)) for i in range(200)]
    assert "".join(shown[a:b] for shown, _, mask in [ch.turn_spans(many, ch.instruct_template, window=5)] for a, b in mask) == "".join(t for _, t in many)


def test_digest_of_odd_conversations(spark):
    rows = [(1, 1, "assistant", "b"), (1, 0, "user", "a"), (1, 1, "assistant", "b"), (2, 0, None, None), (None, 0, "user", "x"), (3, 0, "assistant", "")]
    frame = spark.createDataFrame([(*r, 5) for r in rows], "conv_id long, turn long, role string, text string, formatted int")
    got = {r["conv_id"]: r for r in ch.digest(ch.format_chats(frame.unionByName(ch.control_case(spark), allowMissingColumns=True))).collect()}
    sha = lambda x: hashlib.sha256(x.encode()).hexdigest()
    assert got[1]["turns_sha256"] == sha("user\na\nassistant\nb\nassistant\nb\n") and got[1]["loss_chars"] == 2
    assert got[2]["turns_sha256"] == sha("\n\n") and got[None]["n_turns"] == 1 and got[3]["loss_chars"] == 0
    assert got[-1]["loss_sha256"] == sha("</s>[INST] ok [/INST]")
    assert ch.digest(ch.format_chats(frame.where("false"))).count() == 0


def test_top_k_against_brute_force(spark):
    rng = np.random.default_rng(0)
    rows = [(i, [float(x) for x in rng.normal(size=8)]) for i in range(300)]
    rows += [(300 + i, rows[i][1]) for i in range(20)] + [(400, None), (401, [None] * 8), (402, [float("nan")] * 8), (403, [float("inf")] * 8), (404, [1.0, 2.0]), (405, [1.5, 2.0]), (406, []), (None, [0.0] * 8)]
    frame = spark.createDataFrame([(*r, "l") for r in rows], "vec_id long, embedding array<float>, score string")
    got = top_k(frame, frame.where("vec_id % 10 = 0 or vec_id > 400"), k=5, block=7, rows_at_once=50).collect()
    sound = {i: np.floor(256 * np.array(v, np.float32).astype(float)) for i, v in rows if i is not None and v is not None and all(x is not None and np.isfinite(x) for x in v)}
    for q in [i for i in sound if i % 10 == 0 or i > 400]:
        other = [(-int(sound[q] @ v), i) for i, v in sound.items() if i != q and len(v) == len(sound[q])]
        want = [(n + 1, i, -s) for n, (s, i) in enumerate(sorted(other)[:5])]
        assert sorted((r["rank"], r["vec_id"], r["score"]) for r in got if r["query_id"] == q) == want
    assert top_k(frame.where("false"), frame.where("false")).count() == 0


def test_repeated_vector_ids_are_vectors_of_their_own(spark):
    rows = [(50, [1.0, 0.0]), (50, [0.0, 1.0]), (1, [2.0, 0.0]), (2, [0.0, 2.0]), (2, [0.0, 3.0])]
    frame = spark.createDataFrame(rows, "vec_id long, embedding array<float>")
    got = sorted((r["rank"], r["vec_id"], r["score"]) for r in top_k(frame, frame.where("vec_id = 50"), k=2, block=1).collect())
    assert got == sorted([(1, 1, 131072), (2, 2, 0), (1, 2, 196608), (2, 2, 131072)])


def test_pivots_spare_evaluations():
    rng = np.random.default_rng(2)
    centres = rng.normal(size=(20, 16)) * 400
    vectors = np.floor(np.concatenate([c + rng.normal(size=(100, 16)) * 5 for c in centres]))
    table = PivotTable(np.arange(2000), vectors, 16)
    found = table.top(0, vectors[0], 5)
    scores = vectors @ vectors[0]
    assert [s for s, _ in found] == sorted((int(s) for i, s in enumerate(scores) if i), reverse=True)[:5]
    assert table.evaluated < 1000


def test_pipeline_stages(spark, sf_dir):
    import corpus_pipeline as cp
    from rulegraph.llm.decontaminate import decontaminate
    from rulegraph.llm.neardup import near_duplicates
    from rulegraph.llm.secrets import find

    assert [n for n, _ in cp.STAGES] == ["language_id", "near_duplicates", "decontamination", "secrets", "packing"]
    docs = spark.read.parquet(f"{sf_dir}/documents.parquet")
    odd = spark.createDataFrame([(10**6, None, None, None, None), (10**6 + 1, "12 34 --", "en", "s", 8), (10**6 + 2, "", None, None, None)], docs.schema)
    now = docs.unionByName(odd)
    for name, stage in cp.STAGES[:-1]:
        before = now
        now = stage(spark, now, sf_dir).persist()
        assert now.columns == docs.columns, name
        kept, given = {r["doc_id"] for r in now.collect()}, {r["doc_id"] for r in before.collect()}
        assert kept <= given
        if name == "language_id":
            assert given - kept == {10**6, 10**6 + 1, 10**6 + 2}
        if name == "near_duplicates":
            assert near_duplicates(now).where("class_size > 1").count() == 0
        if name == "decontamination":
            assert decontaminate(before, spark.read.parquet(f"{sf_dir}/benchmark.parquet")).where("contaminated").count() > 0
        if name == "secrets":
            assert not any(find(r["text"]) for r in now.collect())
    named = docs.limit(20).selectExpr("*", "doc_id AS _id", "doc_id AS _node", "1 AS _label", "1 AS _score", "1 AS label", "2 AS score", "3 AS node", "4 AS key", "5 AS spans")
    for name, stage in cp.STAGES[:2]:
        named = stage(spark, named, sf_dir)
        assert named.count() > 0 and named.columns[-9:] == ["_id", "_node", "_label", "_score", "label", "score", "node", "key", "spans"], name
        assert named.where("_id <> doc_id or score <> 2 or key <> 4").count() == 0
    pieces = cp.STAGES[-1][1](spark, now, sf_dir)
    assert {r["doc_id"] for r in pieces.select("doc_id").distinct().collect()} == {r["doc_id"] for r in now.collect()}
