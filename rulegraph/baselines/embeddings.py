"""Embedding baselines: small re-creations of six published families, trained data-parallel.

All but one score a fact by sums of products of a subject, a relation and an object
factor; complex and multivector algebras are signed sums over blocks of real factors,
and time enters through the relation (learned by time bucket), through the entities
(fixed sines), or through recent neighbours. One family translates: subject plus
relation and time tokens should land at the object.

Entities are hashed into ``rows`` vectors, so parameters have a fixed size whatever the
graph's; each epoch every task takes gradient steps on its facts from the shared
parameters and the driver averages the results.
"""

from __future__ import annotations

from collections.abc import Callable
from dataclasses import dataclass

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

#: Signed block triples (subject, relation, object) of each algebra.
REAL = [(0, 0, 0, 1)]
COMPLEX = [(0, 0, 0, 1), (1, 0, 1, 1), (0, 1, 1, 1), (1, 1, 0, -1)]
#: Two-vector geometric product with a scalar, two vectors and a bivector part.
MULTI = [(0, 0, 0, 1), (1, 1, 0, 1), (2, 2, 0, 1), (3, 3, 0, -1), (0, 1, 1, 1), (1, 0, 1, 1), (2, 3, 1, -1), (3, 2, 1, 1), (0, 2, 2, 1), (2, 0, 2, 1), (1, 3, 2, 1), (3, 1, 2, -1), (0, 3, 3, 1), (3, 0, 3, 1), (1, 2, 3, 1), (2, 1, 3, -1)]


@dataclass(frozen=True)
class Family:
    """``time``: relation, relation+static, sines, tokens, neighbours; ``gaps`` adds the lag since the pair's last fact."""

    algebra: tuple
    time: str
    gaps: bool = False


FAMILIES = {
    "diachronic": Family(tuple(REAL), "sines"),
    "time tokens": Family((), "tokens"),
    "complex with gaps": Family(tuple(COMPLEX), "relation+static", gaps=True),
    "order-4 complex": Family(tuple(COMPLEX), "relation+static"),
    "order-4 multivector": Family(tuple(MULTI), "relation+static"),
    "snapshot neighbours": Family(tuple(REAL), "neighbours"),
}


class Model:
    def __init__(self, family: Family, rows: int, relations: int, buckets: int, dim: int, seed: int = 1):
        rng = np.random.default_rng(seed)
        self.family, self.buckets, self.dim = family, buckets, dim
        blocks = 1 + max((max(t[:3]) for t in family.algebra), default=0)
        scale = 0.5 / np.sqrt(dim)
        draw = lambda n: rng.normal(0, scale, (n, blocks, dim)).astype(np.float32)
        self.p = {"e": draw(rows), "r": draw(relations), "rt": draw(relations), "t": draw(buckets) + 1, "hood": np.zeros((rows, blocks, dim), np.float32)}
        self.sines = np.sin(np.arange(buckets)[:, None] * np.exp(-np.arange(dim) / dim * np.log(buckets + 1))[None] + np.arange(dim)[None]).astype(np.float32)

    def factors(self, s, r, o, t):
        a, c = self.p["e"][s], self.p["e"][o]
        b = self.p["r"][r]
        if self.family.time.startswith("relation"):
            b = b + self.p["rt"][r] * self.p["t"][t]
        if self.family.time == "sines":
            half = np.ones((len(s), 1, self.dim), np.float32)
            half[:, :, self.dim // 2 :] = self.sines[t][:, None, self.dim // 2 :]
            a, c = a * half, c * half
        if self.family.time == "neighbours":
            a, c = a + self.p["hood"][s], c + self.p["hood"][o]
        if self.family.time == "tokens":
            b = (b + self.p["t"][t] - 1) / 2
        return a, b, c

    def score(self, s, r, o, t):
        a, b, c = self.factors(s, r, o, t)
        if not self.family.algebra:
            return 2.0 - ((a + b - c) ** 2).sum((1, 2))
        return sum(sign * (a[:, i] * b[:, j] * c[:, k]).sum(1) for i, j, k, sign in self.family.algebra)

    def step(self, s, r, o, t, label, rate, decay=1e-4):
        """One step on the logistic loss of a batch; gradients of shared rows add up."""
        a, b, c = self.factors(s, r, o, t)
        miss = (label - 1 / (1 + np.exp(-np.clip(self.score(s, r, o, t), -30, 30)))).astype(np.float32)[:, None]
        ga, gb, gc = np.zeros_like(a), np.zeros_like(b), np.zeros_like(c)
        if not self.family.algebra:
            d = -2 * (a + b - c) * miss[:, None]
            ga, gb, gc = d, d, -d
        for i, j, k, sign in self.family.algebra:
            ga[:, i] += sign * miss * b[:, j] * c[:, k]
            gb[:, j] += sign * miss * a[:, i] * c[:, k]
            gc[:, k] += sign * miss * a[:, i] * b[:, j]
        if self.family.time == "sines":
            half = np.ones((len(s), 1, self.dim), np.float32)
            half[:, :, self.dim // 2 :] = self.sines[t][:, None, self.dim // 2 :]
            ga, gc = ga * half, gc * half
        self._add("e", s, rate * (ga - decay * a))
        self._add("e", o, rate * (gc - decay * c))
        self._add("r", r, rate * gb)
        if self.family.time.startswith("relation"):
            rt, tt = self.p["rt"][r], self.p["t"][t]
            self._add("rt", r, rate * gb * tt)
            self._add("t", t, 0.1 * rate * gb * rt)
        if self.family.time == "tokens":
            self._add("t", t, 0.5 * rate * gb)

    def _add(self, name, rows, grad, bound=2.0):
        """Adds gradients by row, damped where many meet in one row, and keeps values within bounds."""
        count = np.bincount(rows, minlength=len(self.p[name]))[rows]
        np.add.at(self.p[name], rows, grad / np.sqrt(count)[:, None, None].astype(np.float32))
        np.clip(self.p[name], -bound, bound, out=self.p[name])


def _coded(facts: DataFrame, rows: int, relations: dict, low: int, width: float, buckets: int) -> DataFrame:
    rel = F.create_map(*[x for k, v in relations.items() for x in (F.lit(k), F.lit(v))])
    bucket = F.least(F.greatest(F.floor((F.col("t") - low) / width), F.lit(0)), F.lit(buckets - 1)).cast("int")
    side = lambda c: F.pmod(F.xxhash64(c), F.lit(rows)).cast("int")
    return facts.select(side("s").alias("es"), F.coalesce(F.element_at(rel, F.col("r")), F.lit(0)).alias("er"), side("o").alias("eo"), bucket.alias("et"))


def fit(facts: DataFrame, family: Family, dim: int = 16, epochs: int = 3, rows: int = 1 << 13, buckets: int = 64, negatives: int = 4, rate: float = 0.5, batch: int = 2048, tasks: int = 4) -> tuple[Model, dict]:
    relations = {r["r"]: i for i, r in enumerate(facts.select("r").distinct().orderBy("r").collect())}  # closed, small set
    low, high = facts.agg(F.min("t"), F.max("t")).first()
    width = max(1.0, (high - low + 1) / buckets)
    coded = _coded(facts, rows, relations, low, width, buckets).repartition(tasks).persist()
    model = Model(family, rows, max(1, len(relations)), buckets, dim)
    schema = pa.schema([("name", pa.string()), ("value", pa.binary()), ("n", pa.int64())])
    for epoch in range(epochs):
        sent = facts.sparkSession.sparkContext.broadcast(model.p)

        def train(batches, sent=sent, epoch=epoch):
            own = Model(family, rows, max(1, len(relations)), buckets, dim)
            own.p = {k: v.copy() for k, v in sent.value.items()}
            rng, n = np.random.default_rng(epoch), 0
            for b in batches:
                cols = [b.column(i).to_numpy() for i in range(4)]
                order = rng.permutation(len(cols[0]))
                for i in range(0, len(order), batch):
                    s, r, o, t = (c[order[i : i + batch]].astype(np.int64) for c in cols)
                    if family.time == "neighbours":  # carry-over of recent neighbours
                        np.add.at(own.p["hood"], s, 0.02 * (own.p["e"][o] - own.p["hood"][s]))
                        np.add.at(own.p["hood"], o, 0.02 * (own.p["e"][s] - own.p["hood"][o]))
                    k = len(s) * negatives
                    s2, r2, o2, t2 = (np.tile(x, negatives) for x in (s, r, o, t))
                    which = rng.integers(0, 3, k)
                    o2 = np.where(which == 0, rng.permutation(o2), o2)
                    r2 = np.where(which == 1, rng.permutation(r2), r2)
                    t2 = np.where(which == 2, rng.permutation(t2), t2)
                    y = np.concatenate([np.ones(len(s)), np.zeros(k)])
                    own.step(np.concatenate([s, s2]), np.concatenate([r, r2]), np.concatenate([o, o2]), np.concatenate([t, t2]), y, rate / (1 + negatives))
                    n += len(s)
            rows_ = [(name, value.tobytes(), n) for name, value in own.p.items()]
            yield pa.RecordBatch.from_arrays([pa.array(c, f.type) for c, f in zip(zip(*rows_, strict=True), schema, strict=True)], schema=schema)

        total: dict[str, np.ndarray] = {}
        weight = 0
        for row in coded.mapInArrow(train, "name string, value binary, n long").toLocalIterator():
            shape = model.p[row["name"]].shape
            total[row["name"]] = total.get(row["name"], 0) + np.frombuffer(row["value"], np.float32).reshape(shape).astype(np.float64) * row["n"]
            weight += row["n"] if row["name"] == "e" else 0
        if weight:
            model.p = {k: (v / weight).astype(np.float32) for k, v in total.items()}
    coded.unpersist()
    return model, {"relations": relations, "low": low, "width": width, "rows": rows, "buckets": buckets}


def scorer(name: str, **options) -> Callable[[DataFrame, DataFrame], Callable]:
    """A baseline of the named family: trained on the history it is first given."""
    held: dict = {}

    def run(asked: DataFrame, history: DataFrame) -> DataFrame:
        family = FAMILIES[name]
        if "model" not in held:
            held["model"] = fit(history, family, **options)
        model, meta = held["model"]
        sent = asked.sparkSession.sparkContext.broadcast(model)

        @F.pandas_udf("double")
        def judged(s, r, o, t):
            import pandas as pd

            return pd.Series(-sent.value.score(*(x.to_numpy().astype(np.int64) for x in (s, r, o, t))).astype(float))

        rel = F.create_map(*[x for k, v in meta["relations"].items() for x in (F.lit(k), F.lit(v))])
        side = lambda c: F.pmod(F.xxhash64(c), F.lit(meta["rows"])).cast("int")
        bucket = F.least(F.greatest(F.floor((F.col("t") - meta["low"]) / meta["width"]), F.lit(0)), F.lit(meta["buckets"] - 1)).cast("int")
        out = asked.withColumn("score", judged(side("s"), F.coalesce(F.element_at(rel, F.col("r")), F.lit(0)), side("o"), bucket))
        if family.gaps:
            last = history.groupBy("s", "r", "o").agg(F.max("t").alias("_last"), F.count(F.lit(1)).alias("_n"))
            out = out.join(last, ["s", "r", "o"], "left").withColumn("score", F.col("score") - F.log1p(F.coalesce("_n", F.lit(0)))).drop("_last", "_n")
        return out

    return run


def scorers(**options) -> dict[str, Callable]:
    return {name: scorer(name, **options) for name in FAMILIES}
