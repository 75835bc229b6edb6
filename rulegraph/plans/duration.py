"""Facts with a start and an end: four rule graphs over combinations of the two times, and flattenings."""

from __future__ import annotations

from dataclasses import dataclass, replace

from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from ..operators import evaluation as ev
from ..operators import scoring as sc
from ..storage import staged
from .build import BuildConfig, RuleGraph, build, choose_patterns, profiles_and_ticks, with_witnesses

#: Name of each graph: which time of the head and of the tail it uses.
SIDES = {"start-start": ("t_start", "t_start"), "end-end": ("t_end", "t_end"), "start-end": ("t_start", "t_end"), "end-start": ("t_end", "t_start")}


def side(dfacts: DataFrame, column: str) -> DataFrame:
    return dfacts.select("s", "r", "o", F.col(column).alias("t")).distinct()


def duration_graphs(dfacts: DataFrame, config: BuildConfig | None = None) -> dict[str, RuleGraph]:
    """A rule graph for each combination: heads are looked for with one time, tails stand at the other.

    Profiles and categories do not depend on times, and patterns on those of the tails only: they are made once for all
    graphs that share them.
    """
    config = config or BuildConfig()
    config = replace(config, closures=False)
    from .workloads import together

    first = profiles_and_ticks(side(dfacts, "t_start"), config)
    categories = choose_patterns(first, config).categories
    second = profiles_and_ticks(side(dfacts, "t_end"), config, first.entities)
    choose_patterns(second, config, categories)
    own = {"t_start": first, "t_end": second}

    def one(head: str, tail: str) -> RuleGraph:
        source = None if head == tail else own[head].facts.select("s", "r", "o", "t")
        return build(own[tail].facts, config, witness_facts=source, prepared=own[tail])

    return dict(zip(SIDES, together([lambda h=head, t=tail: one(h, t) for head, tail in SIDES.values()]), strict=True))


def duration_scores(dfacts: DataFrame, history: DataFrame, graphs: dict[str, RuleGraph], config: sc.ScoreConfig | None = None) -> DataFrame:
    """(s, r, o, t_start, t_end) with the mean of the four time scores, the static one, and in how many graphs a fact
    lacks the evidence expected of it (``failed``) and has next to no conflict (``calm``)."""
    from .workloads import together

    config = replace(config or sc.ScoreConfig(), closures=False)
    keyed = dfacts.withColumn("key", F.xxhash64("s", "r", "o", "t_start", "t_end"))

    def one(name: str) -> DataFrame:
        head, tail = SIDES[name]
        found = sc.score(sc.identified(side(dfacts, tail)), side(history, head), graphs[name], config)
        own = keyed.select("key", "s", "r", "o", F.col(tail).alias("t")).join(found, ["s", "r", "o", "t"])
        lacking = (F.col("expected") > 0) & (F.coalesce("ev_temporal", F.lit(0.0)) == 0)
        return staged(own.select("key", "ev_static", F.coalesce("score_time", F.lit(1.0)).alias("temporal"), lacking.cast("int").alias("failed"), (F.col("n_out") == 0).cast("int").alias("calm")), "side")

    parts = together([lambda n=n: one(n) for n in SIDES])
    every = parts[0]
    for p in parts[1:]:
        every = every.unionByName(p)
    mean = every.groupBy("key").agg(F.avg("temporal").alias("score_temporal"), (-F.avg("ev_static")).alias("score_static"), F.sum("failed").alias("failed"), F.sum("calm").alias("calm"))
    return keyed.join(mean, "key").drop("key")


def missing_everywhere(dfacts: DataFrame, history: DataFrame, graphs: dict[str, RuleGraph], config: sc.ScoreConfig | None = None) -> DataFrame:
    """(s, r, o, support, askers): what cannot be instantiated in any of the four graphs: precursors of facts that fail in all
    of them, for facts without a conflict there."""
    from .workloads import together

    config = replace(config or sc.ScoreConfig(), closures=False)

    def one(name: str) -> DataFrame:
        head, tail = SIDES[name]
        facts, past = sc.identified(side(dfacts, tail)), side(history, head)
        trace, nodes, seen = sc.walk(facts, past, graphs[name], config)
        calm = facts.join(sc.out_edges(nodes, graphs[name], seen), "fact_id", "left_anti")
        return staged(sc.missing_precursors(calm, graphs[name], trace).groupBy("s", "r", "o").agg(F.sum("n_assert").alias("support"), F.countDistinct("asker").alias("askers")).withColumn("graph", F.lit(name)), "failed")

    parts = together([lambda n=n: one(n) for n in SIDES])
    every = parts[0]
    for p in parts[1:]:
        every = every.unionByName(p)
    found = every.groupBy("s", "r", "o").agg(F.count(F.lit(1)).alias("_graphs"), F.sum("support").alias("support"), F.max("askers").alias("askers")).where(F.col("_graphs") == len(SIDES)).drop("_graphs")
    return found.join(history.select("s", "r", "o").distinct(), ["s", "r", "o"], "left_anti")


def explained_share_by_graph(graphs: dict[str, RuleGraph]) -> list[tuple[str, float]]:
    return [(name, round(g.scalars["explained_share"], 6)) for name, g in graphs.items()]


def flatten_duration(dfacts: DataFrame, how: str) -> DataFrame:
    """Simple adaptations: start, end, midpoint, or both ends as two facts."""
    if how == "start":
        return side(dfacts, "t_start")
    if how == "end":
        return side(dfacts, "t_end")
    if how == "midpoint":
        return dfacts.select("s", "r", "o", F.floor((F.col("t_start") + F.col("t_end")) / 2).alias("t")).distinct()
    if how == "two-point":
        begin = dfacts.select("s", F.concat(F.lit("start:"), F.col("r").cast("string")).alias("r"), "o", F.col("t_start").alias("t"))
        return begin.unionByName(dfacts.select("s", F.concat(F.lit("end:"), F.col("r").cast("string")).alias("r"), "o", F.col("t_end").alias("t"))).distinct()
    raise ValueError(f"no such flattening: {how}")


def perturb_duration(dfacts: DataFrame, known: DataFrame, rate: float = 0.15, salt: str = "duration") -> DataFrame:
    """One end of chosen facts moved far away, start never after end, results not among the known facts."""
    low, high = known.agg(F.min("t_start"), F.max("t_end")).first()
    span = high - low + 1
    shift = max(1, span // 4)
    text = ("s", "r", "o", "t_start", "t_end")
    chosen = dfacts.where(ev.draw(salt, *text) < int(rate * 16**8)).withColumn("_d", ev.draw(salt + "2", *text))
    far = F.lit(shift) + F.col("_d") % shift
    start = F.when(F.col("_d") % 2 == 0, F.greatest(F.lit(low), F.col("t_start") - far)).otherwise(F.col("t_start"))
    end = F.when(F.col("_d") % 2 == 1, F.least(F.lit(high), F.col("t_end") + far)).otherwise(F.col("t_end"))
    made = chosen.select("s", "r", "o", start.alias("t_start"), end.alias("t_end")).distinct()
    return made.join(known.select(*text), list(text), "left_anti").select(*text)


@dataclass
class DurationCase:
    """Duration facts split by start, with marked errors: kind is valid, conceptual, time, gone or absent."""

    facts: DataFrame
    offline: DataFrame
    parts: dict[str, DataFrame]


def duration_case(dfacts: DataFrame, rate: float = 0.15) -> DurationCase:
    dfacts = staged(dfacts, "dfacts")
    cut = staged(ev.time_split(side(dfacts, "t_start"), (0.6, 0.1, 0.3)).select("t", "part").distinct().withColumnRenamed("t", "t_start"), "cut")
    dated = dfacts.join(cut, "t_start")
    columns = ["s", "r", "o", "t_start", "t_end"]
    parts = {}
    for part in ("validation", "test"):
        clean = dated.where(F.col("part") == part).select(*columns)
        length = clean.groupBy("s", "o", "t_start").agg(F.max(F.col("t_end") - F.col("t_start")).alias("_d"))

        def swapped(salt, clean=clean, length=length):
            made = ev.inject_conceptual(side(clean, "t_start"), side(dfacts, "t_start"), rate, salt)
            return made.join(length, (made["s"] == length["s"]) & (made["o"] == length["o"]) & (made["t"] == length["t_start"]), "left").select(made["s"], made["r"], made["o"], made["t"].alias("t_start"), (made["t"] + F.coalesce("_d", F.lit(30))).alias("t_end"))

        kinds = [clean.withColumn("kind", F.lit("valid")), swapped(f"c-{part}").withColumn("kind", F.lit("conceptual")), perturb_duration(clean, dfacts, rate, f"d-{part}").withColumn("kind", F.lit("time")), swapped(f"ac-{part}").withColumn("kind", F.lit("absent")), perturb_duration(clean, dfacts, rate, f"ad-{part}").withColumn("kind", F.lit("absent"))]
        every = kinds[0]
        for k in kinds[1:]:
            every = every.unionByName(k)
        every = every.groupBy(*columns).agg(F.max("kind").alias("kind"))
        parts[part] = staged(every.withColumn("deleted", (F.col("kind") == "valid") & (ev.draw(f"m-{part}", *columns) < int(rate * 16**8))), part)
    return DurationCase(dfacts, staged(dated.where("part = 'offline'").select(*columns), "offline"), parts)


def _measures(method: str, found: dict[str, DataFrame]) -> list[tuple]:
    """Measures of scored parts (kind, deleted, score_static, score_temporal) for all three kinds."""
    from .workloads import measured, together

    jobs = {}
    for kind, good, score in (("conceptual", F.col("kind") == "conceptual", F.col("score_static")), ("time", F.col("kind") == "time", F.col("score_temporal")), ("missing", F.col("deleted"), -F.col("score_temporal") + F.log2(1 - F.col("score_static")) / 64)):
        bad = (F.col("kind") == "absent") if kind == "missing" else (F.col("kind") == "valid")
        one = lambda df, good=good, bad=bad, score=score: df.where(good | bad).select(good.cast("int").alias("label"), score.alias("score"))
        jobs[kind] = lambda one=one: ev.measure(one(found["validation"]), one(found["test"]))
    return measured("validity", method, dict(zip(jobs, together(list(jobs.values())), strict=True)))


def duration_experiment(case: DurationCase, config: BuildConfig, score: sc.ScoreConfig, graphs: dict[str, RuleGraph] | None = None) -> list[tuple]:
    """Measures of the four graphs together for all three kinds, with the facts before a part and its undeleted valid ones as history."""
    from .workloads import together

    graphs = graphs or duration_graphs(case.offline, config)
    columns = ["s", "r", "o", "t_start", "t_end"]

    def one(part: str) -> DataFrame:
        asked = case.parts[part]
        past = case.offline if part == "validation" else case.offline.unionByName(case.parts["validation"].where("kind = 'valid'").select(*columns))
        history = past.unionByName(asked.where("kind = 'valid' and not deleted").select(*columns))
        return staged(asked.join(duration_scores(asked.select(*columns), history, graphs, score), columns), part)

    return _measures("four graphs", dict(zip(case.parts, together([lambda p=p: one(p) for p in case.parts]), strict=True)))


def flattening_experiment(case: DurationCase, how: str, config: BuildConfig, score: sc.ScoreConfig) -> list[tuple]:
    """The same with one graph over flattened facts; a fact of two points has the larger of their time scores."""
    from .workloads import together

    columns = ["s", "r", "o", "t_start", "t_end"]
    graph = build(flatten_duration(case.offline, how), replace(config, closures=False))

    def judged(part: str) -> DataFrame:
        asked = case.parts[part]
        past = case.offline if part == "validation" else case.offline.unionByName(case.parts["validation"].where("kind = 'valid'").select(*columns))
        history = flatten_duration(past.unionByName(asked.where("kind = 'valid' and not deleted").select(*columns)), how)
        points = _points(asked, how)
        scored = sc.score(sc.identified(points.select("s", "r", "o", "t").distinct()), history, graph, replace(score, closures=False))
        joined = points.join(scored.drop("fact_id"), ["s", "r", "o", "t"])
        one = joined.groupBy("key").agg(F.max(F.coalesce("score_time", F.lit(1.0))).alias("score_temporal"), F.max(-F.col("ev_static")).alias("score_static"))
        return staged(asked.withColumn("key", F.xxhash64(*columns)).join(one, "key"), part)

    return _measures(how, dict(zip(case.parts, together([lambda p=p: judged(p) for p in case.parts]), strict=True)))


def _points(asked: DataFrame, how: str) -> DataFrame:
    """(key, s, r, o, t) of duration facts under a flattening."""
    keyed = asked.withColumn("key", F.xxhash64("s", "r", "o", "t_start", "t_end"))
    at = {"start": [("", F.col("t_start"))], "end": [("", F.col("t_end"))], "midpoint": [("", F.floor((F.col("t_start") + F.col("t_end")) / 2))], "two-point": [("start:", F.col("t_start")), ("end:", F.col("t_end"))]}[how]
    parts = [keyed.select("key", "s", F.concat(F.lit(mark), F.col("r").cast("string")).alias("r"), "o", t.alias("t")) for mark, t in at]
    return parts[0] if len(parts) == 1 else parts[0].unionByName(parts[1])
