"""The online loop on Structured Streaming, and streaming operators on event streams."""

from __future__ import annotations

from collections.abc import Callable
from dataclasses import dataclass, replace

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from ..operators import scoring as sc
from ..operators.updating import OnlineConfig, explained_ticks, should_refresh, update
from ..plans.build import RuleGraph, build
from ..sources.facts import click_facts
from ..storage import new_path, staged


@dataclass
class OnlineState:
    """The graph in use, facts held valid so far, and the counters of the monitor."""

    graph: RuleGraph
    history: DataFrame
    online: dict
    offline: dict
    log: list


def start_state(offline: DataFrame, config) -> OnlineState:
    graph = build(offline, config)
    return OnlineState(graph, offline.select("s", "r", "o", "t"), {"bits": 0.0, "ticks": 0, "facts": 0}, {"bits": graph.scalars["error_bits"], "ticks": graph.scalars["n_ticks"]}, [])


def judged(batch: DataFrame, history: DataFrame, graph: RuleGraph, score: sc.ScoreConfig, online: OnlineConfig) -> DataFrame:
    """Facts of a batch scored and classified.

    A fact may rest on earlier facts of the batch, but never on ones judged wrong: at the first
    look on those that pass the static check, at the next on those that the look before held
    valid. Verdicts of a tick depend on earlier ticks only, so with enough looks nothing changes any
    more and the result is that of one batch a tick; the last change may take as many looks as
    the batch has ticks, so ``online.looks`` bounds them, and smaller batches come nearer.
    """
    facts = sc.identified(batch)
    static = sc.static_score(facts, graph, score)
    own = staged(sc.classify(static.withColumn(online.time_by, F.lit(float("-inf"))), online.th_static, online.th_temporal, online.time_by).where("verdict = 'valid'").select("s", "r", "o", "t"), "static")
    mark = lambda df: tuple(df.agg(F.count(F.lit(1)), F.sum(F.xxhash64("s", "r", "o", "t").bitwiseAND(F.lit((1 << 40) - 1)))).first())
    before, looks = mark(own), 0
    while True:
        scored = staged(sc.classify(sc.score(facts, history.unionByName(own), graph, score), online.th_static, online.th_temporal, online.time_by), "scored")
        looks += 1
        if looks == online.looks:
            return scored
        own = scored.where("verdict = 'valid'").select("s", "r", "o", "t")
        now = mark(own)
        if now == before:
            return scored
        before = now


def advance(state: OnlineState, batch: DataFrame, score: sc.ScoreConfig, online: OnlineConfig, sink: Callable[[DataFrame], None] | None = None, monitor: bool = True) -> tuple[RuleGraph, DataFrame, tuple]:
    """(graph, history, (bits, ticks, facts)) after a batch (staged, a set), before anything is rebuilt: the refresh policy has no part in it."""
    from ..plans.workloads import together

    def watched() -> tuple:  # by graph and history as they were, so while the batch is judged
        return tuple(explained_ticks(batch, state.history, state.graph, state.graph.config.horizon).agg(F.sum("error_bits"), F.count(F.lit(1)), F.sum("n_facts")).first()) if monitor else (0.0, 0, 0)

    def kept() -> tuple[RuleGraph, DataFrame]:
        if online.updater:
            scored = judged(batch, state.history, state.graph, score, online)
        else:  # frozen: the batch sees the history as it is
            scored = staged(sc.classify(sc.score(sc.identified(batch), state.history, state.graph, score), online.th_static, online.th_temporal, online.time_by), "scored")
        if sink:
            sink(scored)
        if not online.updater:
            return state.graph, state.history
        valid, history = scored.where("verdict = 'valid'").select("s", "r", "o", "t"), state.history
        graph, _ = update(state.graph, history, valid)
        # a batch is appended as its own folder: history is not written again
        return graph, history.unionByName(staged(valid.join(history, ["s", "r", "o", "t"], "left_anti"), "history"))

    ticks, (graph, history) = together([watched, kept])
    return graph, history, ticks


def _counted(state: OnlineState, ticks: tuple) -> dict:
    return {"bits": state.online["bits"] + (ticks[0] or 0.0), "ticks": state.online["ticks"] + ticks[1], "facts": state.online["facts"] + (ticks[2] or 0)}


def settled(state: OnlineState, found: tuple[RuleGraph, DataFrame, tuple], online: OnlineConfig, rebuild: Callable[[], RuleGraph] | None = None) -> OnlineState:
    """The state after :func:`advance`, rebuilt when due."""
    graph, history, ticks = found
    counters, offline, rebuilt = _counted(state, ticks), state.offline, False
    if should_refresh(counters, offline, online):
        graph = rebuild() if rebuild else build(history, graph.config)
        offline = {"bits": graph.scalars["error_bits"], "ticks": graph.scalars["n_ticks"]}
        counters, rebuilt = {"bits": 0.0, "ticks": 0, "facts": 0}, True
    return OnlineState(graph, history, counters, offline, [*state.log, {"facts": int(ticks[2] or 0), "bits": float(ticks[0] or 0.0), "rebuilt": rebuilt}])


def step(state: OnlineState, batch: DataFrame, score: sc.ScoreConfig, online: OnlineConfig, sink: Callable[[DataFrame], None] | None = None, monitor: bool = True) -> OnlineState:
    """One micro-batch: score, keep what is valid, update, monitor, rebuild when due."""
    batch = staged(batch.select("s", "r", "o", "t").distinct(), "batch")
    if batch.isEmpty():
        return state
    return settled(state, advance(state, batch, score, online, sink, monitor), online)


def run_online(stream: DataFrame, state: OnlineState, score: sc.ScoreConfig, online: OnlineConfig, sink_path: str) -> OnlineState:
    """Runs the loop over a streaming frame of facts until it has read all that is there.

    Each micro-batch overwrites its own folder, so a repeated batch leaves no second copy.
    """
    held = {"state": state}

    def each(batch: DataFrame, number: int) -> None:
        held["state"] = step(held["state"], batch, score, online, lambda df: df.write.mode("overwrite").parquet(f"{sink_path}/batch={number}"))

    spark = stream.sparkSession
    query = stream.writeStream.foreachBatch(each).option("checkpointLocation", new_path(spark, "stream")).trigger(availableNow=True).start()
    query.awaitTermination()
    return held["state"]


def replay(facts: DataFrame, state: OnlineState, score: sc.ScoreConfig, online: OnlineConfig, bounds: list[int]) -> OnlineState:
    """The same over stored facts, one batch for each interval of ticks."""
    for low, high in zip(bounds[:-1], bounds[1:], strict=True):
        state = step(state, facts.where((F.col("t") >= low) & (F.col("t") < high)), score, online)
    return state


def replay_policies(facts: DataFrame, state: OnlineState, score: sc.ScoreConfig, policies: list[OnlineConfig], bounds: list[int]) -> list[OnlineState]:
    """:func:`replay` for configurations that differ in when they rebuild only: what they have in common is done once.

    Policies go apart with their first different decision; until then (and for rebuilds from one history) graph and history are one.
    """
    from ..plans.workloads import together

    if len({replace(p, refresh="never", refresh_every=0, monitor="cumulative") for p in policies}) > 1:
        raise ValueError("policies may differ in refresh, refresh_every and monitor only")
    at = lambda s: (id(s.graph), id(s.history))
    states = [state] * len(policies)
    for low, high in zip(bounds[:-1], bounds[1:], strict=True):
        batch = staged(facts.where((F.col("t") >= low) & (F.col("t") < high)).select("s", "r", "o", "t").distinct(), "batch")
        if batch.isEmpty():
            continue
        apart = {at(s): s for s in states}
        found = dict(zip(apart, together([lambda s=s: advance(s, batch, score, policies[0]) for s in apart.values()]), strict=True))  # noqa: B023
        due = {at(s): found[at(s)] for s, p in zip(states, policies, strict=True) if should_refresh(_counted(s, found[at(s)][2]), s.offline, p)}
        built = dict(zip(due, together([lambda f=f: build(f[1], f[0].config) for f in due.values()]), strict=True))
        states = [settled(s, found[at(s)], p, lambda s=s: built[at(s)]) for s, p in zip(states, policies, strict=True)]  # noqa: B023
    return states


# ---- streaming operators over the events table -------------------------------------------------------------


def event_stream(spark: SparkSession, sf_dir: str) -> DataFrame:
    """The events table as a stream with a proper timestamp."""
    path = f"{sf_dir}/events.parquet"
    schema = spark.read.parquet(path).schema
    folder, _, name = path.rpartition("/")
    return spark.readStream.schema(schema).option("pathGlobFilter", name).parquet(folder).withColumn("ts", F.col("ts").cast("timestamp"))


def drained(frame: DataFrame, name: str, mode: str = "append") -> DataFrame:
    """Runs a stream over all available input and returns what it wrote.

    In append mode to Parquet; complete results are kept by overwriting each batch.
    """
    spark = frame.sparkSession
    path = new_path(spark, name)
    if mode == "complete":
        writer = frame.writeStream.outputMode("complete").foreachBatch(lambda df, _: df.write.mode("overwrite").parquet(path))
    else:
        writer = frame.writeStream.outputMode(mode).format("parquet").option("path", path)
    query = writer.option("checkpointLocation", new_path(spark, name + "-state")).trigger(availableNow=True).start()
    query.awaitTermination()
    return spark.read.schema(frame.schema).parquet(path)


def tumbling(events: DataFrame) -> DataFrame:
    w = events.groupBy(F.window("ts", "6 hours"), "event_type").agg(F.count(F.lit(1)).alias("n"))
    return w.select(F.unix_seconds("window.start").alias("start"), "event_type", "n")


def sliding(events: DataFrame) -> DataFrame:
    w = events.groupBy(F.window("ts", "1 day", "12 hours"), "event_type").agg(F.count(F.lit(1)).alias("n"))
    return w.select(F.unix_seconds("window.start").alias("start"), "event_type", "n")


def sessions(events: DataFrame) -> DataFrame:
    w = events.groupBy(F.session_window("ts", "2 hours"), "user_id").agg(F.count(F.lit(1)).alias("n"))
    return w.select(F.unix_seconds("session_window.start").alias("start"), "user_id", "n")


def once(events: DataFrame) -> DataFrame:
    """Events without repeats that come within a day."""
    return events.withWatermark("ts", "1 day").dropDuplicatesWithinWatermark(["event_id"])


def deduplicated(events: DataFrame) -> DataFrame:
    return click_facts(once(events))


def late_dropped(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Counts by six hours of a stream whose last file is older than the others by half of the whole span: (start, n).

    Rows are late by the watermark that the batch before began with, so the newest events make a file of their own in between.
    """
    events = spark.read.parquet(f"{sf_dir}/events.parquet").select(F.col("ts").cast("timestamp").alias("ts"))
    low, high = events.agg(F.unix_micros(F.min("ts")), F.unix_micros(F.max("ts"))).first()
    folder = new_path(spark, "late")
    middle = F.timestamp_micros(F.lit((low + high) // 2 // 1_000_000 * 1_000_000))
    newest = F.timestamp_micros(F.lit(high))
    for part in (events.where((F.col("ts") >= middle) & (F.col("ts") < newest)), events.where(F.col("ts") == newest), events.where(F.col("ts") < middle)):
        part.coalesce(1).write.mode("append").parquet(folder)
    stream = spark.readStream.schema(events.schema).option("maxFilesPerTrigger", 1).parquet(folder).withWatermark("ts", "1 hour")
    counted = stream.groupBy(F.window("ts", "6 hours")).agg(F.count(F.lit(1)).alias("n"))
    return drained(counted.select(F.unix_seconds("window.start").alias("start"), "n"), "late-counts")


def scored_stream(stream: DataFrame, graph: RuleGraph) -> DataFrame:
    """Static scores of a stream of facts, one folder a micro-batch, read back."""
    spark = stream.sparkSession
    path = new_path(spark, "static-scores")
    each = lambda batch, i: sc.static_score(sc.identified(batch), graph).write.mode("overwrite").parquet(f"{path}/batch={i}")
    stream.writeStream.foreachBatch(each).option("checkpointLocation", new_path(spark, "static-state")).trigger(availableNow=True).start().awaitTermination()
    return spark.read.parquet(path)


def chain_join(events: DataFrame, hours: int = 6) -> DataFrame:
    """A stream joined with itself: a purchase-like event after another event of the same user within hours."""
    left = events.select(F.col("user_id"), F.col("event_type").alias("head"), F.col("ts").alias("t1"), F.col("event_id").alias("i1")).withWatermark("t1", "1 hour")
    right = events.select(F.col("user_id").alias("u2"), F.col("event_type").alias("tail"), F.col("ts").alias("t2"), F.col("event_id").alias("i2")).withWatermark("t2", "1 hour")
    on = (F.col("user_id") == F.col("u2")) & (F.col("t2") > F.col("t1")) & (F.col("t2") <= F.col("t1") + F.expr(f"interval {hours} hours"))
    return left.join(right, on).select("i1", "i2", "head", "tail")


def pair_state(facts: DataFrame) -> DataFrame:
    """Last tick and number of facts of each pair, kept in the state store across batches."""
    import pandas as pd
    from pyspark.sql.streaming.state import GroupStateTimeout

    def follow(key, frames, state):
        last, n = state.get if state.exists else (-1, 0)
        for frame in frames:
            last, n = max(last, int(frame["t"].max())), n + len(frame)
        state.update((last, n))
        yield pd.DataFrame({"s": [key[0]], "o": [key[1]], "last": [last], "n": [n]})

    return facts.groupBy("s", "o").applyInPandasWithState(follow, "s string, o string, last long, n long", "last long, n long", "update", GroupStateTimeout.NoTimeout)
