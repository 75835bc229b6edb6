"""The experiments: data sets with injected errors, methods and variants, measures, parameter sweeps."""

from __future__ import annotations

import time
from collections.abc import Callable
from concurrent.futures import ThreadPoolExecutor
from dataclasses import dataclass, replace

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from ..operators import evaluation as ev
from ..operators import scoring as sc
from ..operators.categories import CategoryConfig
from ..operators.updating import OnlineConfig
from ..sources import facts as fx
from ..storage import staged
from ..streaming import online as stream
from .build import BuildConfig, Occurrences, RuleGraph, build, prepare, ready

#: Witnesses and lags of interest, in ticks, for each fixture.
SETTINGS = {"lifecycle": {"horizon": 30, "L": 2, "legs": 5, "criterion": "errors"}, "trade": {"horizon": 200, "L": 10, "legs": 10}, "clicks": {"horizon": 240, "L": 12, "legs": 6}, "dialogue": {"horizon": 20, "L": 1, "legs": 2}}


@dataclass
class Experiment:
    """Facts split by time; validation and test with injected errors of three kinds."""

    name: str
    facts: DataFrame
    offline: DataFrame
    parts: dict[str, dict[str, DataFrame]]


def experiment(facts: DataFrame, name: str, rate: float = 0.15, fractions=(0.6, 0.1, 0.3)) -> Experiment:
    """Every part holds ``asked``: (s, r, o, t, kind), what a method sees or is asked about.

    kind is valid, conceptual or time for what arrives. Missing facts are a task of their own: valid facts marked ``deleted``
    are taken out of the history then, and told from perturbed ones that never arrive (absent).
    """
    facts = staged(facts, "facts")
    low, high = facts.agg(F.min("t"), F.max("t")).first()
    cut = staged(ev.time_split(facts, fractions), "split")
    offline = cut.where("part = 'offline'").select("s", "r", "o", "t")
    parts = {}
    for part in ("validation", "test"):
        clean = cut.where(F.col("part") == part).select("s", "r", "o", "t")
        kinds = [clean.withColumn("kind", F.lit("valid"))]
        for salt, mark in (("conceptual", "conceptual"), ("absent-c", "absent")):
            kinds.append(ev.inject_conceptual(clean, facts, rate, f"{salt}-{part}").withColumn("kind", F.lit(mark)))
        for salt, mark in (("time", "time"), ("absent-t", "absent")):
            kinds.append(ev.inject_time(clean, facts, rate, f"{salt}-{part}", low=low, high=high).withColumn("kind", F.lit(mark)))
        every = kinds[0]
        for k in kinds[1:]:
            every = every.unionByName(k)
        # perturbations that coincide count once, for the last kind by name; none equals a valid fact
        every = every.groupBy("s", "r", "o", "t").agg(F.max("kind").alias("kind"))
        deleted = (F.col("kind") == "valid") & ev.is_missing(rate, f"missing-{part}")
        asked = staged(every.withColumn("deleted", deleted), part)
        of = lambda kind: asked.where(F.col("kind") == kind).select("s", "r", "o", "t")  # noqa: B023, E731
        gone = asked.where("deleted").select("s", "r", "o", "t")
        parts[part] = {"asked": asked, "valid": of("valid"), "time": of("time"), "conceptual": of("conceptual"), "gone": gone, "left": asked.where("kind = 'valid' and not deleted").select("s", "r", "o", "t"), "stream": asked.where("kind <> 'absent'").select("s", "r", "o", "t", "kind"), "missing": asked.where("deleted or kind = 'absent'").select("s", "r", "o", "t", F.when(F.col("deleted"), "gone").otherwise("absent").alias("kind"))}
    return Experiment(name, facts, offline, parts)


def of_fixture(spark: SparkSession, sf_dir: str, name: str, **options) -> Experiment:
    return experiment(fx.FIXTURES[name](spark, sf_dir), name, **options)


def build_config(name: str, **changes) -> BuildConfig:
    own = SETTINGS.get(name, {"horizon": None, "L": 5, "legs": 5})
    return replace(BuildConfig(horizon=own["horizon"], L=own["legs"], criterion=own.get("criterion", "total")), **changes)


def score_config(name: str, **changes) -> sc.ScoreConfig:
    own = SETTINGS.get(name, {"horizon": None, "L": 5, "legs": 5})
    return replace(sc.ScoreConfig(horizon=own["horizon"], L=own["L"], closure_window=own["legs"]), **changes)


def together(jobs: list[Callable], at_once: int = 4) -> list:
    """Results of independent runs, a few at once: their many small jobs share the cluster."""
    with ThreadPoolExecutor(at_once) as pool:
        return [f.result() for f in [pool.submit(job) for job in jobs]]


Scorer = Callable[[DataFrame, DataFrame], DataFrame]
KINDS = ("conceptual", "time", "missing")
#: What each kind of error is told apart from: (kind of positives, of negatives, column of the score).
TASKS = {"conceptual": ("conceptual", "valid", "s_conceptual"), "time": ("time", "valid", "s_time"), "missing": ("gone", "absent", "s_missing")}


@dataclass
class Run:
    """What a method said: (s, r, o, t, kind, s_conceptual, s_time, s_missing) of validation and test, and how it got there."""

    validation: DataFrame
    test: DataFrame
    history: DataFrame
    graph: RuleGraph | None
    online: OnlineConfig | None
    facts: int
    seconds: float

    def measures(self, kinds=KINDS) -> dict[str, dict]:
        def judged(kind: str) -> dict:
            good, bad, column = TASKS[kind]
            one = lambda df: df.where(F.col("kind").isin(good, bad)).select((F.col("kind") == good).cast("int").alias("label"), F.col(column).alias("score"), "t")
            return ev.measure(one(self.validation), one(self.test))

        return dict(zip(kinds, together([lambda k=k: judged(k) for k in kinds]), strict=True))

    def rate(self) -> float:
        return round(self.facts / max(1e-9, self.seconds), 1)


def scores(found: DataFrame, form: str = "expectation") -> DataFrame:
    """The three anomaly scores as finite numbers. ``form`` of the time score: ``expectation``, or ``evidence``: its negative
    with no evidence at all ranked first, as the published reciprocal does."""
    static = -F.col("ev_static").cast("double")
    plain = -F.coalesce("ev_temporal", F.lit(0.0)) / (1 + F.col("n_out"))
    time_ = F.coalesce("score_time", F.lit(1.0)) if form == "expectation" else plain
    level = F.least(F.lit(1.0), F.log2(1 + F.coalesce(F.col("ev_static"), F.lit(0.0))) / 64)
    return found.withColumn("s_conceptual", static).withColumn("s_time", time_).withColumn("s_missing", (level - time_) / 2)


def _scored(asked: DataFrame, history: DataFrame, graph: RuleGraph, config: sc.ScoreConfig, name: str, seen: DataFrame | None = None) -> DataFrame:
    found = sc.score(sc.identified(asked), history, graph, config, seen=seen)
    return staged(asked.join(found.drop("fact_id"), ["s", "r", "o", "t"]), name)


def detect(exp: Experiment, graph: RuleGraph, config: sc.ScoreConfig, updater: bool = True, batches: int = 3, form: str = "expectation") -> Run:
    """The whole method over the test part as a stream of batches: score, judge, keep what is judged valid, update.

    Validation comes with its labels: they give the thresholds, and its valid facts are history.
    From then on no label is seen: later batches rest on verdicts only. Deleted and absent
    facts are asked about at the end, against what was kept. Without the updater graph and
    history stay as they were after validation.
    """
    began = time.time()
    v = exp.parts["validation"]
    history = exp.offline.unionByName(v["valid"])
    validation = scores(_scored(v["stream"], history, graph, config, "validation"), form)
    cut = {}
    for kind in ("conceptual", "time"):
        good, bad, column = TASKS[kind]
        cut[kind], _ = ev.best_threshold(ev.pr_curve(validation.where(F.col("kind").isin(good, bad)).select((F.col("kind") == good).cast("int").alias("label"), F.col(column).alias("score"))))
    th_time = cut["time"] if form == "expectation" else 1.0 / max(1e-300, -cut["time"])
    # the thresholds themselves are still flagged
    online = OnlineConfig(updater=updater, refresh="never", th_static=1.0 / (max(0.0, -cut["conceptual"]) + 0.5), th_temporal=th_time - abs(th_time) * 1e-12 - 1e-300, time_by="score_time" if form == "expectation" else "score_temporal")
    state = stream.OnlineState(graph, history, {"bits": 0.0, "ticks": 0, "facts": 0}, {"bits": 0.0, "ticks": 1}, [])
    arriving = exp.parts["test"]["stream"]
    low, high, n = arriving.agg(F.min("t"), F.max("t"), F.count(F.lit(1))).first()
    held: list[DataFrame] = []
    bounds = [low + (high + 1 - low) * i // batches for i in range(batches + 1)] if updater else [low, high + 1]
    for a, b in zip(bounds[:-1], bounds[1:], strict=True):
        state = stream.step(state, arriving.where((F.col("t") >= a) & (F.col("t") < b)).drop("kind"), config, online, held.append, monitor=False)
    seconds = time.time() - began
    every = held[0]
    for one in held[1:]:
        every = every.unionByName(one)
    test = scores(arriving.join(every, ["s", "r", "o", "t"]).select(*COLUMNS), form)
    run = Run(validation.select(*test.columns), test, state.history, state.graph, online, n, seconds)
    return with_missing(exp, run, state.graph, config, form)


COLUMNS = ["s", "r", "o", "t", "kind", "ev_static", "ev_temporal", "score_time", "score_temporal", "expected", "n_in", "n_out"]


def with_missing(exp: Experiment, run: Run, graph: RuleGraph, config: sc.ScoreConfig, form: str = "expectation") -> Run:
    """Adds what the method says of deleted and absent facts, against the kept history without the deleted ones."""
    def one(part: str, scored: DataFrame) -> DataFrame:
        kept = exp.offline.unionByName(exp.parts[part]["left"]) if part == "validation" else run.history.join(exp.parts[part]["gone"], ["s", "r", "o", "t"], "left_anti")
        asked = scores(_scored(exp.parts[part]["missing"], kept, graph, config, "asked").select(*COLUMNS), form)
        return staged(scored.unionByName(asked.select(*scored.columns)), part)

    validation, test = together([lambda: one("validation", run.validation), lambda: one("test", run.test)])
    return replace(run, validation=validation, test=test)


def witnesses_of(exp: Experiment, run: Run, config: sc.ScoreConfig) -> dict[str, DataFrame]:
    """Witnesses of all arriving facts against the history that a run kept, for sweeps that differ later only."""
    early = exp.offline.unionByName(exp.parts["validation"]["valid"])
    return {part: staged(sc.seen_before(sc.identified(exp.parts[part]["stream"]), early if part == "validation" else run.history, run.graph, config), "seen") for part in exp.parts}


def against_kept(exp: Experiment, run: Run, graph: RuleGraph, config: sc.ScoreConfig, form: str = "expectation", seen: dict[str, DataFrame] | None = None, missing: bool = False) -> Run:
    """Another graph or other scores over the same stream, resting on the history that ``run`` kept by its verdicts."""
    began = time.time()
    early = exp.offline.unionByName(exp.parts["validation"]["valid"])
    out = {part: scores(_scored(exp.parts[part]["stream"], early if part == "validation" else run.history, graph, config, part, seen and seen[part]).select(*COLUMNS), form) for part in exp.parts}
    n = sum(out[p].count() for p in out)
    found = Run(out["validation"], out["test"], run.history, graph, run.online, n, time.time() - began)
    return with_missing(exp, found, graph, config, form) if missing else found


def plain(exp: Experiment, scorer: Scorer) -> Run:
    """A baseline with one score for all kinds (high: anomalous); history is all before the test part."""
    began = time.time()
    early = exp.offline.unionByName(exp.parts["validation"]["left"])
    out = {}
    for part, history in (("validation", exp.offline), ("test", early)):
        asked = exp.parts[part]["asked"].withColumn("label", F.lit(0))
        found = scorer(asked, history)
        found = found.unionByName(found.where("deleted").withColumn("kind", F.lit("gone")))
        out[part] = staged(found.select("s", "r", "o", "t", "kind", F.col("score").alias("s_conceptual"), F.col("score").alias("s_time"), (-F.col("score")).alias("s_missing")), part)
    n = sum(exp.parts[p]["asked"].count() for p in out)
    return Run(out["validation"], out["test"], early, None, None, n, time.time() - began)


MEASURES = "experiment string, method string, kind string, precision double, recall double, f05 double, pr_auc double, roc_auc double"


def rows_of(spark: SparkSession, rows: list[tuple]) -> DataFrame:
    return spark.createDataFrame(rows, MEASURES)


def measured(name: str, method: str, found: dict[str, dict]) -> list[tuple]:
    return [(name, method, kind, *(round(float(m[x]), 6) for x in ("precision", "recall", "f05", "pr_auc", "roc_auc"))) for kind, m in found.items()]


#: Variants of the build and of the scores, one at a time.
def variants(name: str) -> dict[str, tuple[BuildConfig, sc.ScoreConfig, bool]]:
    b, s = build_config(name), score_config(name)
    return {
        "full": (b, s, True),
        "no category aggregation": (replace(b, categories=replace(b.categories, aggregate=False)), s, True),
        "no updater": (b, s, False),
        "no closure links": (replace(b, closures=False), replace(s, closures=False), True),
        "no recursion": (b, replace(s, K=0), True),
        "ranking by assertions only": (replace(b, rank_by="assertions"), s, True),
        "unit weights in scores": (b, replace(s, weight="unit"), True),
    }


def ablation(exp: Experiment, run: Run, only: tuple[str, ...] | None = None, kinds=KINDS) -> list[tuple]:
    """Measures of variants: one preparation, a graph for each different build, all resting on what ``run`` kept.

    Without the updater the test part is judged anew, with graph and history as they were before it.
    """
    prepared = prepare(exp.offline, build_config(exp.name))
    chosen = {m: v for m, v in variants(exp.name).items() if not only or m in only}
    builds = list({b for b, _, _ in chosen.values()} - {build_config(exp.name)})
    built = dict(zip(builds, together([lambda b=b: build(exp.offline, b, prepared=prepared) for b in builds]), strict=True)) | {build_config(exp.name): run.graph}

    def judged(method: str) -> list[tuple]:
        b, s, updater = chosen[method]
        if not updater:
            found = detect(exp, built[b], s, updater=False)
        else:
            found = run if method == "full" else against_kept(exp, run, built[b], s, missing="missing" in kinds)
        return measured(exp.name, method, found.measures(kinds))

    return [row for rows in together([lambda m=m: judged(m) for m in chosen]) for row in rows]


def sweep_row(exp: Experiment, parameter: str, value: float, run: Run, kind: str) -> tuple:
    m = run.measures((kind,))[kind]
    return (exp.name, kind, parameter, float(value), round(m["pr_auc"], 6), round(m["f05"], 6), round(run.seconds, 3), run.rate())


def score_sweep(exp: Experiment, run: Run, configs: dict[float, sc.ScoreConfig], parameter: str, kind: str = "time") -> list[tuple]:
    """Accuracy and throughput of score settings, all over one table of witnesses."""
    seen = witnesses_of(exp, run, next(iter(configs.values())))
    return [sweep_row(exp, parameter, v, against_kept(exp, run, run.graph, c, seen=seen), kind) for v, c in configs.items()]


def depth_sweep(exp: Experiment, run: Run, depths=(0, 1, 2, 3, 4)) -> list[tuple]:
    return score_sweep(exp, run, {k: score_config(exp.name, K=k) for k in depths}, "K")


def window_sweep(exp: Experiment, run: Run, windows=(1, 5, 10, 50, 200)) -> list[tuple]:
    return score_sweep(exp, run, {w: score_config(exp.name, L=w) for w in windows}, "L")


def category_sweep(exp: Experiment, run: Run, ks=(1, 3, 5, 10)) -> list[tuple]:
    prepared = prepare(exp.offline, build_config(exp.name))

    def one(k: int) -> tuple:
        graph = build(exp.offline, build_config(exp.name, categories=CategoryConfig(k=k)), prepared=prepared)
        return sweep_row(exp, "k", k, against_kept(exp, run, graph, score_config(exp.name)), "conceptual")

    return together([lambda k=k: one(k) for k in ks])


def proportion_sweep(exp: Experiment, run: Run, shares=(0.2, 0.4, 0.6, 0.8, 1.0), kinds=("conceptual", "time")) -> list[tuple]:
    """Accuracy of graphs built from the latest share of the offline ticks only."""
    low, high = exp.offline.agg(F.min("t"), F.max("t")).first()

    def one(share: float) -> list[tuple]:
        graph = run.graph if share == 1.0 else build(exp.offline.where(F.col("t") >= high - (high - low) * share), build_config(exp.name))
        found = against_kept(exp, run, graph, score_config(exp.name))
        return [sweep_row(exp, "share", share, found, kind) for kind in kinds]

    return [row for rows in together([lambda s=s: one(s) for s in shares]) for row in rows]


def over_time(exp: Experiment, run: Run, kind: str, ticks: int, unseen: bool = False) -> DataFrame:
    """Precision and recall by bins of ticks at the threshold chosen on validation; ``unseen``: only triples that no offline fact holds."""
    good, bad, column = TASKS[kind]
    own = lambda df: df.where(F.col("kind").isin(good, bad)).select("s", "r", "o", "t", (F.col("kind") == good).cast("int").alias("label"), F.col(column).alias("score"))
    threshold, _ = ev.best_threshold(ev.pr_curve(own(run.validation)))
    test = own(run.test)
    if unseen:
        test = test.join(exp.offline.select("s", "r", "o").distinct(), ["s", "r", "o"], "left_anti")
    return ev.accuracy_over_time(test, threshold, ticks)


def grid_search(exp: Experiment, run: Run, depths=(0, 2), windows=(1, 10)) -> list[tuple]:
    """Score settings by the best F-score on validation; the chosen one has rank 1."""
    seen = witnesses_of(exp, run, score_config(exp.name))
    rows = []
    for k in depths:
        for w in windows:
            found = against_kept(exp, run, run.graph, score_config(exp.name, K=k, L=w), seen=seen)
            own = lambda df: df.where("kind in ('valid', 'time')").select((F.col("kind") == "time").cast("int").alias("label"), F.col("s_time").alias("score"))
            _, f = ev.best_threshold(ev.pr_curve(own(found.validation)))
            rows.append((exp.name, k, w, round(f, 6), round(found.measures(("time",))["time"]["f05"], 6)))
    order = sorted(rows, key=lambda x: (-x[3], x[1], x[2]))
    return [(*row, order.index(row) + 1) for row in rows]


SWEEP = "experiment string, kind string, parameter string, value double, pr_auc double, f05 double, seconds double, facts_per_s double"
GRID = "experiment string, k int, l int, f05_validation double, f05_test double, rank int"


def build_report(facts: DataFrame, name: str, ks=(1, 3, 5, 10)) -> list[tuple]:
    """Seconds, links, patterns and explained share by number of categories, one build after the other. What no category changes
    (witnesses, counts by profiles, frequent combinations of relations) is made once, with its seconds under k = 0."""
    began = time.time()
    prepared = ready(facts, build_config(name))
    out = [(name, 0.0, round(time.time() - began, 3), 0, 0, 0.0, 0.0, False)]
    for k in ks:
        began = time.time()
        x = build(facts, build_config(name, categories=CategoryConfig(k=k)), prepared=prepared).scalars
        out.append((name, float(k), round(time.time() - began, 3), int(x["n_links"]), int(x["n_patterns"]), round(x["explained_share"], 6), round(x["total_bits"], 3), x["converged"]))
    return out


REPORT = "experiment string, k double, seconds double, n_links long, n_patterns long, explained_share double, total_bits double, converged boolean"
