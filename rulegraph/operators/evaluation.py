"""Splits by time, injected errors with their truth, and accuracy measures.

Random choices are md5 draws of a fact's text, so they repeat on any engine and
partitioning.
"""

from __future__ import annotations

from pyspark.sql import DataFrame, Window
from pyspark.sql import functions as F

from .running import running_sums


def draw(salt: str, *columns, digits: int = 8):
    """An integer below 16**digits from the md5 of the columns' text."""
    text = F.concat_ws("|", F.lit(salt), *[F.col(c).cast("string") for c in columns])
    return F.conv(F.substring(F.md5(text), 1, digits), 16, 10).cast("long")


def time_split(facts: DataFrame, fractions: tuple[float, float, float] = (0.6, 0.1, 0.3)) -> DataFrame:
    """Adds part (offline, validation, test): distinct ticks in order, cut by their number."""
    ticks = facts.select("t").distinct()
    total = ticks.count()
    place = F.row_number().over(Window.orderBy("t"))  # one row a tick
    first, second = int(total * fractions[0]), int(total * (fractions[0] + fractions[1]))
    parts = ticks.withColumn("_i", place).select("t", F.when(F.col("_i") <= first, "offline").when(F.col("_i") <= second, "validation").otherwise("test").alias("part"))
    return facts.join(parts, "t")


def offline_end(facts: DataFrame, fractions: tuple[float, float, float] = (0.6, 0.1, 0.3)) -> int | None:
    """The last tick of the offline part of :func:`time_split`; None where that part is empty."""
    ticks = sorted(row[0] for row in facts.select("t").distinct().collect())  # one row a tick
    first = int(len(ticks) * fractions[0])
    return ticks[first - 1] if first else None


def _chosen(facts: DataFrame, rate: float, salt: str) -> DataFrame:
    return facts.where(draw(salt, "s", "r", "o", "t") < int(rate * 16**8))


def inject_conceptual(facts: DataFrame, known: DataFrame, rate: float = 0.15, salt: str = "conceptual", buckets: int = 256) -> DataFrame:
    """Errors made from facts by another object (even draws) or relation (odd): no triple of ``known`` among them.

    The other object is the least entity of a hash bucket, so the choice needs a table of
    ``buckets`` rows only.
    """
    ends = known.select(F.col("o").alias("e")).distinct()
    other = ends.withColumn("_b", draw("bucket", "e") % buckets).groupBy("_b").agg(F.min("e").alias("_e"))
    rels = known.select("r").distinct()
    rels = rels.withColumn("_j", F.row_number().over(Window.orderBy("r")) - 1)
    n_rel = rels.count()
    base = _chosen(facts, rate, salt).withColumn("_d", draw(salt + "2", "s", "r", "o", "t"))
    by_object = base.where("_d % 2 = 0").withColumn("_b", F.floor(F.col("_d") / 2) % buckets).join(F.broadcast(other), "_b").where("_e <> s").select("s", "r", F.col("_e").alias("o"), "t")
    by_relation = base.where("_d % 2 = 1").withColumn("_j", (F.floor(F.col("_d") / 2) % n_rel).cast("int")).select("s", "o", "t", "_j").join(F.broadcast(rels), "_j").select("s", "r", "o", "t")
    made = by_object.unionByName(by_relation).distinct()
    return made.join(known.select("s", "r", "o").distinct(), ["s", "r", "o"], "left_anti").select("s", "r", "o", "t")


def inject_time(facts: DataFrame, known: DataFrame, rate: float = 0.15, salt: str = "time", min_shift: int | None = None, low: int | None = None, high: int | None = None) -> DataFrame:
    """Errors with a tick at least min_shift (a quarter of the span by default) away, wrapped into low..high."""
    if low is None or high is None:
        low, high = facts.agg(F.min("t"), F.max("t")).first()
    span = high - low + 1
    shift = min_shift if min_shift is not None else max(1, span // 4)
    moved = _chosen(facts, rate, salt).withColumn("_d", draw(salt + "2", "s", "r", "o", "t"))
    made = moved.select("s", "r", "o", (F.lit(low) + (F.col("t") - low + shift + F.col("_d") % max(1, span - 2 * shift)) % span).alias("t")).distinct()
    return made.join(known.select("s", "r", "o", "t"), ["s", "r", "o", "t"], "left_anti").select("s", "r", "o", "t")


def is_missing(rate: float, salt: str):
    """Whether a fact (s, r, o, t) is among the deleted ones."""
    return draw(salt, "s", "r", "o", "t") < int(rate * 16**8)


def inject_missing(facts: DataFrame, rate: float = 0.15, salt: str = "missing") -> tuple[DataFrame, DataFrame]:
    """(facts left, facts deleted)."""
    gone = is_missing(rate, salt)
    return facts.where(~gone), facts.where(gone)


def pr_curve(scored: DataFrame, score: str = "score", label: str = "label") -> DataFrame:
    """(score, tp, fp, precision, recall) for each distinct score, the highest first; ties are one step."""
    steps = scored.groupBy(F.col(score).alias("score")).agg(F.sum(F.col(label).cast("long")).alias("p"), F.sum(1 - F.col(label).cast("long")).alias("n"))
    total = steps.agg(F.sum("p")).first()[0] or 0
    curve = running_sums(steps, [F.desc("score")], {"tp": "p", "fp": "n"})
    return curve.select("score", "p", "n", "tp", "fp", F.try_divide(F.col("tp"), F.col("tp") + F.col("fp")).alias("precision"), F.try_divide(F.col("tp"), F.lit(float(total))).alias("recall"))


def area_under_pr(curve: DataFrame) -> float:
    """Step-wise area: precision times the recall gained at each distinct score."""
    total = curve.agg(F.max("tp")).first()[0]
    return float(curve.agg(F.sum(F.col("precision") * F.col("p") / total)).first()[0] or 0.0) if total else 0.0


def area_under_roc(curve: DataFrame) -> float:
    total = curve.agg(F.max("tp").alias("p"), F.max("fp").alias("n")).first()
    if not total["p"] or not total["n"]:
        return 0.0
    return float(curve.agg(F.sum(F.col("n") * (F.col("tp") - F.col("p") / 2))).first()[0]) / (total["p"] * total["n"])


def best_threshold(curve: DataFrame, beta: float = 0.5) -> tuple[float, float]:
    """(score, F) of the step with the largest F-score."""
    b = beta * beta
    f = (1 + b) * F.col("precision") * F.col("recall") / (b * F.col("precision") + F.col("recall"))
    row = curve.where("tp > 0 and score is not null").select("score", f.alias("f")).orderBy(F.desc("f"), F.desc("score")).first()
    return (float(row["score"]), float(row["f"])) if row else (float("inf"), 0.0)


def at_threshold(scored: DataFrame, threshold: float, score: str = "score", label: str = "label", beta: float = 0.5) -> dict:
    """Precision, recall and F at score >= threshold."""
    hit = F.col(score) >= threshold
    one = lambda c: F.sum(c.cast("long"))
    tp, fp, fn = scored.agg(one(hit & (F.col(label) == 1)), one(hit & (F.col(label) == 0)), one(~hit & (F.col(label) == 1))).first()
    tp, fp, fn = tp or 0, fp or 0, fn or 0
    b = beta * beta
    return {"precision": tp / max(1, tp + fp), "recall": tp / max(1, tp + fn), "f": (1 + b) * tp / max(1e-12, (1 + b) * tp + b * fn + fp)}


def measure(validation: DataFrame, test: DataFrame, beta: float = 0.5) -> dict:
    """Threshold by the best F on validation, then precision, F, PR area and ROC area on test (score, label)."""
    threshold, _ = best_threshold(pr_curve(validation), beta)
    curve = pr_curve(test)
    found = at_threshold(test, threshold, beta=beta)
    return {"precision": found["precision"], "recall": found["recall"], "f05": found["f"], "pr_auc": area_under_pr(curve), "roc_auc": area_under_roc(curve)}


def accuracy_over_time(scored: DataFrame, threshold: float, ticks: int) -> DataFrame:
    """Precision, recall and counts for bins of ticks."""
    hit = (F.col("score") >= threshold).cast("long")
    out = scored.groupBy(F.floor(F.col("t") / ticks).alias("bin")).agg(F.sum(hit * F.col("label")).alias("tp"), F.sum(hit * (1 - F.col("label"))).alias("fp"), F.sum((1 - hit) * F.col("label")).alias("fn"))
    return out.withColumn("precision", F.try_divide("tp", F.col("tp") + F.col("fp"))).withColumn("recall", F.try_divide("tp", F.col("tp") + F.col("fn")))
