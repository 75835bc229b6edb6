"""Baselines on plain DataFrame operators: counts, personalised PageRank change, frequency factorisation, context features.

Each takes (asked, history) with facts (s, r, o, t) and gives asked with a score, high for anomalous.
"""

from __future__ import annotations

# imported here: baselines run in threads, and threads that import pyspark.ml at once can fail
from pyspark.ml.classification import LogisticRegression
from pyspark.ml.feature import VectorAssembler
from pyspark.ml.functions import vector_to_array
from pyspark.ml.recommendation import ALS
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from ..storage import staged


def counts(asked: DataFrame, history: DataFrame) -> DataFrame:
    """How seldom the fact's pairs of parts occur: the floor that every method should beat."""
    out = asked
    for i, pair in enumerate((("s", "r"), ("r", "o"), ("s", "o"))):
        n = history.groupBy(*pair).agg(F.count(F.lit(1)).alias(f"_n{i}"))
        out = out.join(n, list(pair), "left")
    seen = sum(F.log2(1.0 + F.coalesce(F.col(f"_n{i}"), F.lit(0))) for i in range(3))
    return out.withColumn("score", -seen).drop("_n0", "_n1", "_n2")


def pagerank_change(asked: DataFrame, history: DataFrame, ticks: int = 60, seeds: int = 8, alpha: float = 0.15, rounds: int = 3) -> DataFrame:
    """Change of personalised PageRank vectors of a fact's ends between its snapshot and the one before.

    Seeds are the entities with the least hashes; vectors of all snapshots advance together, one
    join and one aggregate a round.
    """
    facts = history.select("s", "o", "t").unionByName(asked.select("s", "o", "t")).withColumn("snap", F.floor(F.col("t") / ticks))
    edges = facts.select("snap", F.col("s").alias("u"), F.col("o").alias("v")).unionByName(facts.select("snap", F.col("o").alias("u"), F.col("s").alias("v"))).groupBy("snap", "u", "v").agg(F.count(F.lit(1)).alias("w"))
    share = edges.join(edges.groupBy("snap", "u").agg(F.sum("w").alias("total")), ["snap", "u"]).select("snap", "u", "v", (F.col("w") / F.col("total")).alias("w"))
    share = staged(share, "edges")
    chosen = facts.select(F.col("s").alias("seed")).distinct().orderBy(F.xxhash64("seed")).limit(seeds)
    start = share.select("snap").distinct().crossJoin(F.broadcast(chosen)).select("snap", "seed", F.col("seed").alias("node"), F.lit(1.0).alias("p"))  # seeds times snapshots rows
    rank = start
    for _ in range(rounds):
        moved = rank.join(share, (rank["snap"] == share["snap"]) & (rank["node"] == share["u"])).select(rank["snap"], "seed", F.col("v").alias("node"), ((1 - alpha) * F.col("p") * F.col("w")).alias("p"))
        again = start.withColumn("p", F.lit(alpha))
        rank = staged(moved.unionByName(again).groupBy("snap", "seed", "node").agg(F.sum("p").alias("p")), "ranks")
    later = rank.select((F.col("snap") + 1).alias("snap"), "seed", "node", (-F.col("p")).alias("p"))
    change = rank.unionByName(later).groupBy("snap", "seed", "node").agg(F.sum("p").alias("p")).groupBy("snap", "node").agg(F.sum(F.abs("p")).alias("change"))
    out = asked.withColumn("snap", F.floor(F.col("t") / ticks))
    for end in ("s", "o"):
        out = out.join(change.select("snap", F.col("node").alias(end), F.col("change").alias(f"_{end}")), ["snap", end], "left")
    return out.withColumn("score", F.coalesce("_s", F.lit(0.0)) + F.coalesce("_o", F.lit(0.0))).drop("snap", "_s", "_o")


def frequency_factors(asked: DataFrame, history: DataFrame, rank: int = 8, rounds: int = 5, ticks: int = 60) -> DataFrame:
    """Surprise of a pair's count in a snapshot under a factorised rate of interaction."""
    key = lambda c: F.pmod(F.xxhash64(c), F.lit((1 << 31) - 1)).cast("int")
    span = history.agg(((F.max("t") - F.min("t")) / ticks + 1).alias("n")).first()["n"] or 1.0
    rates = history.groupBy("s", "o").agg(F.count(F.lit(1)).alias("n")).select(key("s").alias("u"), key("o").alias("v"), F.log1p(F.col("n") / float(span)).cast("float").alias("rate"))
    model = ALS(rank=rank, maxIter=rounds, userCol="u", itemCol="v", ratingCol="rate", nonnegative=True, coldStartStrategy="nan", seed=1).fit(rates)
    seen = asked.withColumn("snap", F.floor(F.col("t") / ticks))
    k = seen.groupBy("s", "o", "snap").agg(F.count(F.lit(1)).alias("k"))
    told = model.transform(seen.join(k, ["s", "o", "snap"]).withColumn("u", key("s")).withColumn("v", key("o")))
    lam = F.greatest(F.expm1(F.coalesce(F.nanvl(F.col("prediction").cast("double"), F.lit(0.0)), F.lit(0.0))), F.lit(1e-6))
    surprise = lam - F.col("k") * F.log(lam)
    return told.withColumn("score", surprise).drop("u", "v", "k", "snap", "prediction")


def context(asked: DataFrame, history: DataFrame, seed_rate: float = 0.15) -> DataFrame:
    """Features of a fact's surroundings (counts, degrees, recency) under a logistic regression trained on swapped facts."""
    from ..operators.evaluation import inject_conceptual, inject_time

    names = ["sr", "ro", "so", "ds", "do", "ls", "lo"]

    def features(facts: DataFrame) -> DataFrame:
        out = facts
        for name, keys in (("sr", ["s", "r"]), ("ro", ["r", "o"]), ("so", ["s", "o"]), ("ds", ["s"]), ("do", ["o"])):
            out = out.join(history.groupBy(*keys).agg(F.log1p(F.count(F.lit(1))).alias(name)), keys, "left")
        for name, keys in (("ls", ["s", "r"]), ("lo", ["r", "o"])):
            out = out.join(history.groupBy(*keys).agg(F.max("t").alias(f"_{name}")), keys, "left").withColumn(name, F.log1p(F.abs(F.col("t") - F.coalesce(F.col(f"_{name}"), F.col("t") - 10000)))).drop(f"_{name}")
        return VectorAssembler(inputCols=names, outputCol="features").transform(out.fillna(0.0, names))

    bad = inject_conceptual(history, history, seed_rate, "context").unionByName(inject_time(history, history, seed_rate, "context-t")).withColumn("label", F.lit(1.0))
    good = history.select("s", "r", "o", "t").withColumn("label", F.lit(0.0))
    model = LogisticRegression(maxIter=20, regParam=0.01).fit(features(good.unionByName(bad)))
    found = model.transform(features(asked.withColumnRenamed("label", "_label") if "label" in asked.columns else asked))
    out = found.withColumn("score", vector_to_array("probability")[1]).drop("features", "rawPrediction", "probability", "prediction", *names)
    return out.withColumnRenamed("_label", "label") if "label" in asked.columns else out


METHODS = {"counts": counts, "pagerank change": pagerank_change, "frequency factors": frequency_factors, "context features": context}
"""Baselines that need no training loop of ours."""
