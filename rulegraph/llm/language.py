"""Language identification with a linear-chain conditional random field over words.

Words get features of their affixes (first and last one to three bytes), their byte
trigrams and a lexicon entry (the whole word), hashed into ``buckets`` rows of
weights; transitions between the labels of neighbouring words are learned too. Chains
are runs of ``chain`` words of a text; forward-backward gives each word's posterior,
and a text's language is the one with the largest mean posterior over all its words.

Training chains partly join two texts of different languages, so that switching
inside a text is learned as rare rather than impossible.
"""

from __future__ import annotations

from dataclasses import dataclass

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame, Window
from pyspark.sql import functions as F
from pyspark.sql import types as T

from .common import blocks_of, mix64, tidied, words_of

_AFFIXES = 7
_OUT = pa.schema([("doc_id", pa.int64()), ("held_out", pa.bool_()), ("lang_pred", pa.string()), ("score", pa.float64())])
_DDL = "doc_id long, held_out boolean, lang_pred string, score double"


@dataclass
class Features:
    """Hashed features of distinct words: a fixed number of affixes each, trigrams by bounds."""

    affixes: np.ndarray
    trigrams: np.ndarray
    starts: np.ndarray


def word_features(lower: np.ndarray, starts: np.ndarray, ends: np.ndarray, hashes: np.ndarray, buckets: int) -> Features:
    """Features of words given as slices of lower-cased bytes; row ``buckets`` of the weights stays 0."""
    length = ends - starts
    total = np.cumsum(length + 1)
    begin = total - length  # one separator before each word
    flat = np.zeros((int(total[-1]) if len(total) else 0) + 2, np.uint64)
    inside = np.repeat(begin - np.concatenate([[0], np.cumsum(length)[:-1]]), length) + np.arange(length.sum()) if len(total) else np.zeros(0, np.int64)
    source = np.repeat(starts - np.concatenate([[0], np.cumsum(length)[:-1]]), length) + np.arange(length.sum()) if len(total) else np.zeros(0, np.int64)
    flat[inside] = lower[source]
    out = np.empty((len(starts), _AFFIXES), np.int64)
    out[:, 0] = mix64(hashes ^ np.uint64(0x51ED)) % np.uint64(buckets)
    head = np.zeros(len(starts), np.uint64)
    tail = np.zeros(len(starts), np.uint64)
    last = begin + length - 1
    for k in range(3):
        held = k < length
        head |= np.where(held, flat[np.minimum(begin + k, len(flat) - 1)], 0).astype(np.uint64) << np.uint64(8 * k)
        tail |= np.where(held, flat[np.maximum(last - k, 0)], 0).astype(np.uint64) << np.uint64(8 * k)
        out[:, 1 + k] = mix64(head | np.uint64((2 * k + 2) << 40)) % np.uint64(buckets)
        out[:, 4 + k] = mix64(tail | np.uint64((2 * k + 3) << 40)) % np.uint64(buckets)
    if not len(starts):
        return Features(out, np.zeros(0, np.int64), np.zeros(0, np.int64))
    three = flat[:-2] | (flat[1:-1] << np.uint64(8)) | (flat[2:] << np.uint64(16))
    grams = np.full(len(flat), buckets, np.int64)
    grams[1:-1] = mix64(three | np.uint64(99 << 40)) % np.uint64(buckets)
    grams[flat == 0] = buckets
    return Features(out, grams, begin)


def emissions(features: Features, weights: np.ndarray) -> np.ndarray:
    out = weights[features.affixes].sum(1)
    if len(features.starts):
        out += np.add.reduceat(weights[features.trigrams], features.starts, axis=0)
    return out


def chains_of(bounds: np.ndarray, chain: int) -> tuple[np.ndarray, np.ndarray]:
    """Runs of at most ``chain`` words that do not cross texts: first words and lengths."""
    n = np.diff(bounds)
    count = -(-n // chain)
    text = np.repeat(np.arange(len(n)), count)
    nth = np.arange(len(text)) - np.repeat(np.cumsum(count) - count, count)
    first = bounds[:-1][text] + nth * chain
    return first, np.minimum(chain, bounds[1:][text] - first)


def passed_on(local: np.ndarray, bounds: np.ndarray, first: np.ndarray, length: np.ndarray, step: np.ndarray) -> tuple[np.ndarray, np.ndarray]:
    """What enters each run of a text from the runs before it, and what comes back from those after it.

    A run is a linear map of the messages that pass through it. The maps of all runs are
    multiplied out together; then messages go from run to run of each text, so the runs of a text
    are one chain, however long it is.
    """
    runs, labels = len(first), local.shape[1]
    enter, leave = np.ones((runs, labels), local.dtype), np.ones((runs, labels), local.dtype)
    text = np.searchsorted(bounds, first, "right") - 1
    several = np.bincount(text, minlength=len(bounds))[text] > 1 if runs else np.zeros(0, bool)
    own = np.flatnonzero(several)
    if not len(own):
        return enter, leave
    first, length, text = first[own], length[own], text[own]
    order = np.argsort(-length, kind="stable")
    through = np.zeros((len(own), labels, labels), local.dtype)
    through[:, np.arange(labels), np.arange(labels)] = local[first]
    for t in range(1, int(length.max())):
        live = order[: np.searchsorted(-length[order], -t, "left")]
        now = (through[live] @ step) * local[first[live] + t][:, None, :]
        through[live] = now / now.max((1, 2), keepdims=True)
    head = np.flatnonzero(np.concatenate([[True], text[1:] != text[:-1]]))
    count = np.diff(np.concatenate([head, [len(own)]]))
    into, back = np.ones((len(own), labels), local.dtype), np.ones((len(own), labels), local.dtype)
    for j in range(1, int(count.max())):
        at = head[count > j] + j
        now = np.einsum("rl,rlm->rm", into[at - 1], through[at - 1]) @ step
        into[at] = now / now.max(1, keepdims=True)
        at = head[count > j] + count[count > j] - 1 - j
        now = np.einsum("rlm,rm->rl", through[at + 1], back[at + 1]) @ step.T
        back[at] = now / now.max(1, keepdims=True)
    enter[own], leave[own] = into, back
    return enter, leave


def forward_backward(score: np.ndarray, first: np.ndarray, length: np.ndarray, transitions: np.ndarray, bounds: np.ndarray | None = None) -> tuple[np.ndarray, np.ndarray, float]:
    """Posteriors of the words of chains, expected transition counts, and the sum of log partitions.

    With ``bounds`` (of texts) the runs of a text are joined to one chain, and the posteriors are those of
    the whole text; counts and partitions are then those of the runs given what enters them.

    All chains advance together; within a step each is rescaled, so nothing overflows.
    """
    labels = score.shape[1]
    top = score.max(1, keepdims=True)
    local = np.exp(score - top)
    step = np.exp(transitions).astype(score.dtype)
    enter, leave = passed_on(local, bounds, first, length, step) if bounds is not None else (None, None)
    order = np.argsort(-length, kind="stable")
    first, length = first[order], length[order]
    live = np.searchsorted(-length, -np.arange(1, (int(length[0]) if len(length) else 0) + 1), "right")
    ahead = np.empty_like(local)
    log_z = float(top.sum()) if len(score) else 0.0
    for t, n in enumerate(live):
        at = first[:n] + t
        a = (local[at] if enter is None else local[at] * enter[order[:n]]) if t == 0 else (ahead[at - 1] @ step) * local[at]
        norm = a.sum(1, keepdims=True)
        ahead[at] = a / norm
        log_z += float(np.log(norm).sum())
    posterior = ahead.copy()
    pairs = np.zeros((labels, labels))
    back = np.ones((len(first), labels), score.dtype) if leave is None else leave[order]
    if leave is not None and len(first):
        at = first + length - 1
        posterior[at] = ahead[at] * back / (ahead[at] * back).sum(1, keepdims=True)
    for t in range(len(live) - 1, 0, -1):
        n = live[t]
        at = first[:n] + t
        future = local[at] * back[:n]
        before = future @ step.T
        joint = ahead[at - 1] * before
        norm = joint.sum(1, keepdims=True)
        pairs += step * ((ahead[at - 1] / norm).T @ future)
        before /= before.sum(1, keepdims=True)
        back[:n] = before
        posterior[at - 1] = joint / norm
    return posterior, pairs, log_z


@dataclass
class LanguageModel:
    labels: list[str]
    weights: np.ndarray
    transitions: np.ndarray
    chain: int

    @property
    def buckets(self) -> int:
        return len(self.weights) - 1

    def posteriors(self, data: np.ndarray, offsets: np.ndarray) -> tuple[np.ndarray, np.ndarray]:
        """Sum of word posteriors by text, and the number of its words."""
        starts, ends, hashes, bounds = words_of(data, offsets)
        return self._texts(data, starts, ends, hashes, bounds)

    def _texts(self, data, starts, ends, hashes, bounds):
        n = len(bounds) - 1
        if not len(starts) or not self.labels:
            return np.zeros((n, len(self.labels))), np.zeros(n)
        posterior = self.words(data, starts, ends, hashes, bounds)
        total = np.zeros((len(starts) + 1, posterior.shape[1]))
        np.cumsum(posterior, axis=0, out=total[1:])
        return total[bounds[1:]] - total[bounds[:-1]], np.diff(bounds)

    def words(self, data, starts, ends, hashes, bounds) -> np.ndarray:
        """Posteriors of each word: labels of a code-switched text, word by word."""
        from .common import WORD_LUT

        _, one, which = np.unique(hashes, return_index=True, return_inverse=True)
        features = word_features(WORD_LUT[data], starts[one], ends[one], hashes[one], self.buckets)
        score = emissions(features, self.weights)[which]
        # maps of runs cost labels**2 a word: with many labels a text is one run
        first, length = chains_of(bounds, self.chain if len(self.labels) <= 16 else max(1, int(np.diff(bounds).max(initial=1))))
        return forward_backward(score, first, length, self.transitions, bounds)[0]


def spread_runs(first: int, last: int, words_each: int, chain: int) -> list[np.ndarray]:
    """Runs of at most ``chain`` words of a text, ``words_each`` words in all, with even gaps from its first word to its last."""
    n = min(last - first, words_each)
    begins = range(0, n, chain)
    spare = last - first - n
    return [first + spare * k // max(1, len(begins) - 1) + np.arange(i, min(i + chain, n)) for k, i in enumerate(begins)]


def train(texts: list[str], langs: list[str], buckets: int = 1 << 16, chain: int = 64, words_each: int = 400, steps: int = 30, rate: float = 0.3, mixed: float = 0.3, seed: int = 7) -> LanguageModel:
    """Maximum likelihood by full-batch AdaGrad on chains cut from the texts: all words, or ``words_each`` spread evenly over the text."""
    labels = sorted(set(langs))
    if not labels:
        return LanguageModel([], np.zeros((buckets + 1, 0), np.float32), np.zeros((0, 0), np.float32), chain)
    raw = [t.encode("utf-8", "replace") for t in texts]
    data = np.frombuffer(b"".join(raw), np.uint8)
    offsets = np.concatenate([[0], np.cumsum([len(x) for x in raw])]).astype(np.int64)
    starts, ends, hashes, bounds = words_of(data, offsets)
    number = {x: i for i, x in enumerate(labels)}
    rng = np.random.default_rng(seed)
    runs = [(own, number[lang]) for a, b, lang in zip(bounds[:-1], bounds[1:], langs, strict=True) for own in spread_runs(int(a), int(b), words_each, chain)]
    if not runs:
        return LanguageModel(labels, np.zeros((buckets + 1, len(labels)), np.float32), np.zeros((len(labels), len(labels)), np.float32), chain)
    words, truth, sizes = [], [], []
    other = rng.permutation(len(runs))
    for k, (own, lang) in enumerate(runs):
        if rng.random() < mixed:
            second, label = runs[other[k]]
            a, b = own[: max(1, len(own) // 2)], second[: max(1, len(second) // 2)]
            words += [a, b]
            truth += [np.full(len(a), lang), np.full(len(b), label)]
            sizes.append(len(a) + len(b))
        else:
            words.append(own)
            truth.append(np.full(len(own), lang))
            sizes.append(len(own))
    words, truth, length = np.concatenate(words), np.concatenate(truth), np.array(sizes)
    first = np.cumsum(length) - length
    from .common import WORD_LUT

    _, one, which = np.unique(hashes[words], return_index=True, return_inverse=True)
    one = words[one]
    features = word_features(WORD_LUT[data], starts[one], ends[one], hashes[one], buckets)
    gram_word = np.repeat(np.arange(len(one)), np.diff(np.concatenate([features.starts, [len(features.trigrams)]])))
    grams = features.trigrams[features.starts[0] :]
    n = len(labels)
    weights, transitions = np.zeros((buckets + 1, n), np.float32), np.zeros((n, n), np.float32)
    seen_w, seen_t = np.full_like(weights, 1e-8), np.full_like(transitions, 1e-8)
    inner = np.ones(len(words), bool)
    inner[first] = False
    to = np.flatnonzero(inner)
    observed = np.zeros((n, n))
    np.add.at(observed, (truth[to - 1], truth[to]), 1)
    hot = np.eye(n, dtype=np.float32)[truth]
    for _ in range(steps):
        posterior, pairs, _ = forward_backward(emissions(features, weights)[which], first, length, transitions)
        miss = hot - posterior
        grad = np.empty_like(weights)
        for y in range(n):
            by_word = np.bincount(which, miss[:, y], len(one))
            grad[:, y] = np.bincount(features.affixes.ravel(), np.repeat(by_word, _AFFIXES), buckets + 1) + np.bincount(grams, by_word[gram_word], buckets + 1)
        grad = grad / len(length) - 1e-4 * weights
        grad[buckets] = 0
        seen_w += grad**2
        weights += (rate * grad / np.sqrt(seen_w)).astype(np.float32)
        slope = ((observed - pairs) / len(length) - 1e-3 * transitions).astype(np.float32)
        seen_t += slope**2
        transitions += rate * slope / np.sqrt(seen_t)
    return LanguageModel(labels, weights, transitions, chain)


def held_out() -> F.Column:
    """True for documents that training never sees: crc32 of the id's digits is 2 modulo 4."""
    return F.coalesce(F.pmod(F.crc32(F.encode(F.col("doc_id").cast("string"), "UTF-8")), F.lit(4)) == 2, F.lit(False))


def excerpt(chars: int, pieces: int = 8) -> F.Column:
    """The text, or pieces of it from its beginning to its end that hold ``chars`` characters in all."""
    each = max(1, chars // pieces)
    spare = F.length("text") - each
    parts = [F.substring(F.col("text"), (F.floor(spare * k / (pieces - 1)) + 1).cast("int"), F.lit(each)) for k in range(pieces)]
    return F.when(F.length("text") <= chars, F.col("text")).otherwise(F.concat_ws(" ", *parts))


def fit(docs: DataFrame, per_label: int = 200, text_bytes: int = 20_000, **options) -> LanguageModel:
    """Learns from labelled documents (doc_id, text, lang) that are not held out.

    All labels are learned. The sample is bounded: about ``per_label`` documents of each
    label, drawn by a hash of the id, of each the whole text or, if it is longer, eight
    pieces of ``text_bytes`` characters in all, spread over it, and of these the words that
    ``train`` takes (training only; prediction reads whole texts). The model's size grows
    with the labels. No labelled document gives a model without labels.
    """
    labelled = docs.where(~held_out() & F.col("lang").isNotNull() & F.col("text").isNotNull() & F.col("doc_id").isNotNull())
    counts = labelled.groupBy("lang").agg(F.count(F.lit(1)).alias("n")).collect()
    if not counts:
        return train([], [], **options)
    share = F.create_map(*[x for r in counts for x in (F.lit(r["lang"]), F.lit(min(1.0, per_label / r["n"])))])
    unit = F.xxhash64("doc_id", F.lit(3)).bitwiseAND(F.lit((1 << 53) - 1)).cast("double") / float(1 << 53)
    sample = labelled.where(unit < F.element_at(share, F.col("lang"))).select("doc_id", "lang", excerpt(text_bytes).alias("text"))
    nth = Window.partitionBy("lang").orderBy(F.xxhash64("doc_id", F.lit(3)), "doc_id", "text")
    rows = sample.withColumn("_n", F.row_number().over(nth)).where(F.col("_n") <= 2 * per_label).drop("_n").collect()
    rows.sort(key=lambda r: (r["doc_id"], r["text"]))
    return train([r["text"] for r in rows], [r["lang"] for r in rows], **options)


def _has_letters(data: np.ndarray) -> bool:
    if (((data | 32) >= 97) & ((data | 32) <= 122)).any():
        return True
    return bool((data >= 128).any()) and any(c.isalpha() for c in data.tobytes().decode("utf-8", "ignore"))


def predict_batch(model: LanguageModel, batch: pa.RecordBatch, block_bytes: int = 1 << 20):
    """(first row, labels, scores) for the texts of a batch, block by block."""
    for first, n, data, offsets in blocks_of(batch, limit=block_bytes):
        total, words = model.posteriors(data, offsets)
        ascii_letter = np.concatenate([[0], np.cumsum(((data | 32) >= 97) & ((data | 32) <= 122))])
        letters = ascii_letter[offsets[1:]] > ascii_letter[offsets[:-1]]
        for i in np.flatnonzero(~letters):
            letters[i] = _has_letters(data[offsets[i] : offsets[i + 1]])
        sound = letters & (words > 0) & bool(model.labels)
        best = total.argmax(1) if model.labels else np.zeros(n, np.int64)
        score = np.zeros(n)
        score[sound] = np.clip(total[sound, best[sound]] / words[sound], 0, 1)
        yield first, [model.labels[b] if s else "und" for b, s in zip(best.tolist(), sound.tolist(), strict=True)], score


def identify(docs: DataFrame, model: LanguageModel) -> DataFrame:
    """Language and score of documents (doc_id, text): one row for each input row.

    A text that is null or has no letter is ``und`` with score 0, as is everything under a
    model without labels; repeated rows are judged each; an empty table gives no rows.
    """
    sent = docs.sparkSession.sparkContext.broadcast(model)

    def predict(batches):
        for batch in batches:
            for first, labels, score in predict_batch(sent.value, batch):
                yield pa.RecordBatch.from_arrays([batch.column(0).slice(first, len(labels)), batch.column(2).slice(first, len(labels)), pa.array(labels, pa.string()), pa.array(score)], schema=_OUT)

    return docs.select(F.col("doc_id").cast("long").alias("doc_id"), "text", held_out().alias("held_out")).mapInArrow(tidied(predict), _DDL)


def with_language(docs: DataFrame, model: LanguageModel, label: str, score: str) -> DataFrame:
    """All rows and columns of docs with the predicted language and its score as two more columns."""
    sent = docs.sparkSession.sparkContext.broadcast(model)

    def judge(batches):
        for batch in batches:
            labels, scores = [], []
            for _, own, found in predict_batch(sent.value, batch):
                labels += own
                scores += found.tolist()
            yield pa.RecordBatch.from_arrays([*batch.columns, pa.array(labels, pa.string()), pa.array(scores, pa.float64())], [*batch.schema.names, label, score])

    schema = T.StructType([*docs.schema.fields, T.StructField(label, T.StringType()), T.StructField(score, T.DoubleType())])
    return docs.mapInArrow(tidied(judge), schema)
