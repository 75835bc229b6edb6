"""Scores of new facts against a rule graph, and the evidence behind them.

Static evidence counts assertions of the selected patterns that a fact maps to. Temporal
evidence walks the links backward from those patterns: a precursor that something earlier
in the pair (or over a corner) instantiates adds the pattern's weight, damped by how its
time span fits the link's kept lags; one that nothing instantiates is replaced by its own
precursors, up to K times. Both scores are reciprocals: high means anomalous, null (no
evidence at all) means most anomalous.

Evidence alone cannot tell a fact that lacks what always comes before it from one that
nothing need come before, so a third score, ``score_time``, sets the evidence found
against what the graph expects: every link into the fact's patterns is expected to give
its weight times the share of the pattern's facts that it explained and their mean fit.
"""

from __future__ import annotations

from dataclasses import dataclass

from pyspark.sql import DataFrame, Window
from pyspark.sql import functions as F

from ..plans.build import RuleGraph, _expanded, corner_cats, profiled, small, with_profiles
from ..storage import staged
from .occurrences import NO_CORNER, chain_witnesses, closure_kinds, closure_witnesses, earlier_chains, half_edges, latest_witnesses, linked_closures, with_earlier


@dataclass(frozen=True)
class ScoreConfig:
    """``gap``: how lags damp evidence (``literal``: by the number of agreeing lags, as printed; ``mismatch``: by
    the number of disagreeing ones; ``agreement``: by the share that agrees). ``weight``: assertions or unit."""

    K: int = 2
    L: int = 5
    gap: str = "agreement"
    weight: str = "assertions"
    lam: float = 0.0
    dedupe: bool = False
    out_edge_penalty: bool = True
    horizon: int | None = None
    closures: bool = True
    closure_window: int = 5


def identified(facts: DataFrame) -> DataFrame:
    return facts.select(F.xxhash64("s", "r", "o", "t").alias("fact_id"), "s", "r", "o", "t")


def _weight(config: ScoreConfig):
    return F.col("n_assert").cast("double") if config.weight == "assertions" else F.lit(1.0)


def static_score(facts: DataFrame, graph: RuleGraph, config: ScoreConfig | None = None) -> DataFrame:
    """Adds ev_static and score_static; entities or patterns never seen give evidence 0 and a null score."""
    config = config or ScoreConfig()
    held = profiled(facts, graph.categories, "left")
    cells = held.select("ps", "r", "po").where("ps is not null and po is not null").distinct()
    patterns = graph.patterns.where("selected").select("cs", "r", "co", _weight(config).alias("w"))
    evidence = _expanded(cells, graph.categories).join(patterns, ["cs", "r", "co"]).groupBy("ps", "r", "po").agg(F.sum("w").alias("ev_static"))
    out = held.join(small(evidence, graph.categories), ["ps", "r", "po"], "left").withColumn("ev_static", F.coalesce("ev_static", F.lit(0.0)))
    return out.select(*facts.columns, "ev_static", F.try_divide(F.lit(1.0), F.col("ev_static")).alias("score_static"))


def near_table(lags: DataFrame, tolerance: int) -> DataFrame:
    """(cand, lag, near): kept lags within tolerance of each lag that can have any; at most ticks + 2 tolerance rows a link."""
    ends = lags.groupBy("cand").agg(F.min("lag").alias("lo"), F.max("lag").alias("hi"))
    dense = ends.select("cand", F.explode(F.sequence(F.greatest(F.col("lo") - tolerance, F.lit(0)), F.col("hi") + tolerance)).alias("lag"))
    around = Window.partitionBy("cand").orderBy("lag").rangeBetween(-tolerance, tolerance)
    return dense.join(lags.select("cand", "lag", "cnt"), ["cand", "lag"], "left").select("cand", "lag", F.coalesce(F.sum("cnt").over(around), F.lit(0)).alias("near"))


def fit_factor(gap: str):
    """How the lag of a witness damps its evidence, from ``near`` and ``total`` kept lags."""
    near = F.coalesce("near", F.lit(0))
    if gap == "literal":
        return 1.0 / (near + 1)
    if gap == "mismatch":
        return 1.0 / (F.col("total") - near + 1)
    return near / F.col("total")


def weighed_links(graph: RuleGraph, config: ScoreConfig) -> tuple[DataFrame, DataFrame]:
    """Links (cand, wid, cx, cs, co, r, w, total, usual, expected) and the near table.

    ``usual`` is the most frequent lag (the least of equals); ``expected`` the evidence that a link gives to a
    fact of its tail on average: w times share explained times mean agreement of lags.
    """
    key = (config.L, config.weight)
    if key in graph.memo:
        return graph.memo[key]
    near = staged(near_table(graph.lags, config.L), "near")
    own = graph.lags.join(near, ["cand", "lag"])
    fits = own.groupBy("cand").agg(F.sum("cnt").alias("total"), F.sum(F.col("cnt") * F.col("near")).alias("_hit"), F.max(F.struct("cnt", (-F.col("lag")).alias("neg"))).alias("_m"))
    tails = graph.patterns.select("cs", "r", "co", _weight(config).alias("w"), F.col("n_assert").cast("double").alias("_n"))
    share = F.least(F.lit(1.0), F.coalesce(F.col("n_cover") / F.col("_n"), F.lit(0.0)))
    mean = F.col("_hit") / (F.col("total").cast("double") * F.col("total"))
    links = graph.links if "n_cover" in graph.links.columns else graph.links.withColumn("n_cover", F.col("n_assert"))
    out = links.select("cand", "wid", "cx", "cs", "co", "r", "n_cover").join(fits, "cand").join(tails, ["cs", "r", "co"], "left")
    out = out.select("cand", "wid", "cx", "cs", "co", "r", F.coalesce("w", F.lit(1.0)).alias("w"), "total", (-F.col("_m.neg")).alias("usual"), (F.coalesce("w", F.lit(0.0)) * share * mean).alias("expected"))
    graph.memo[key] = staged(out, "weighed"), near
    return graph.memo[key]


def in_sight(history: DataFrame, facts: DataFrame, ticks: int | None) -> DataFrame:
    """History that facts can still see: from ``ticks`` before the first to the last. The filter reaches the scan."""
    if ticks is None:
        return history
    low, high = facts.agg(F.min("t"), F.max("t")).first()
    return history if low is None else history.where((F.col("t") >= low - ticks) & (F.col("t") <= high))


def seen_before(facts: DataFrame, history: DataFrame | None, graph: RuleGraph, config: ScoreConfig) -> DataFrame:
    """(fact_id, wid, cx, lag, t_seen): latest witnesses of facts in history (None: the facts themselves), with the corner's categories.

    All chains, and of closures the kinds that the graph's links start from.
    """
    if history is None and config.horizon is not None and not (config.closures and graph.config.closures):
        found = earlier_chains(facts.select("fact_id", "s", "r", "o", "t"), config.horizon, latest=True)
        return found.select("fact_id", "wid", F.col("corner").alias("cx"), "lag", "t_seen")
    history = facts.select("s", "r", "o", "t") if history is None else history
    history = in_sight(history, facts, None if config.horizon is None else config.horizon + config.closure_window)
    own = history.join(facts.select("s", "o").distinct(), ["s", "o"], "left_semi")
    witnesses = chain_witnesses(own)
    kinds = linked_closures(graph.links, history) if config.closures and graph.config.closures else None
    if kinds is not None:
        witnesses = witnesses.unionByName(closure_witnesses(history, graph.categories.entities, facts, config.closure_window, config.horizon, kinds))
    seen = latest_witnesses(facts, witnesses, config.horizon).join(corner_cats(graph.categories), "corner")
    return seen.groupBy("fact_id", "wid", "cx").agg(F.min("lag").alias("lag"), F.max("t_seen").alias("t_seen"))


def nodes_of(facts: DataFrame, graph: RuleGraph, *more: str) -> DataFrame:
    """(fact_id, cs, co, r): the graph's patterns that facts map to, with ``more`` columns of the facts."""
    cells = profiled(facts, graph.categories).select("fact_id", "ps", "r", "po", *more)
    known = _expanded(cells.select("ps", "r", "po").distinct(), graph.categories).join(graph.patterns.select("cs", "r", "co").distinct(), ["cs", "r", "co"], "left_semi")
    found = cells.join(small(known, graph.categories), ["ps", "r", "po"]).select("fact_id", "cs", "co", "r", *more)
    return found if graph.categories.named else found.distinct()  # a kind is its profile's only category


def walk(facts: DataFrame, history: DataFrame | None, graph: RuleGraph, config: ScoreConfig, seen: DataFrame | None = None, kept: bool = True) -> tuple[DataFrame, DataFrame, DataFrame]:
    """The trace (fact_id, hop, cand, wid, cx, cs, co, r, mult, back, lag, contribution, expected, status), nodes and witnesses.

    The frontier is kept by (fact, node) with a multiplicity, so it never holds more rows
    than facts times nodes; a failed chain precursor is expanded, a failed closure is not,
    as its legs lie in other pairs. ``back``: usual lags on the way to the node. Not ``kept``: for who only counts the trace;
    where facts are their own history, kinds categories and links chains, no table of it is written then.
    """
    if not kept and seen is None and history is None and config.horizon is not None and graph.categories.named and not (config.closures and graph.config.closures):
        return _walk_pairs(facts, graph, config), nodes_of(facts, graph), seen_before(facts, None, graph, config)
    seen = staged(seen_before(facts, history, graph, config), "seen") if seen is None else seen
    links, near = (small(x, graph.categories) for x in weighed_links(graph, config))
    heads = graph.patterns.select("r").distinct().select(F.xxhash64(F.lit("chain"), "r").alias("wid"), F.col("r").alias("r_head"))
    nodes = nodes_of(facts, graph)
    frontier, trace = nodes.withColumn("mult", F.lit(1).cast("long")).withColumn("back", F.lit(0).cast("long")), None
    for hop in range(config.K + 1):
        met = frontier.join(links, ["cs", "co", "r"]).join(seen, ["fact_id", "wid", "cx"], "left").join(near, ["cand", "lag"], "left")
        contribution = F.when(F.col("lag").isNotNull(), F.col("mult") * F.col("w") * fit_factor(config.gap)).otherwise(0.0)
        status = F.when(F.col("lag").isNotNull(), "ok").when((F.col("cx") == NO_CORNER) & F.lit(hop < config.K), "expanded").otherwise("failed")
        level = staged(met.select("fact_id", F.lit(hop).alias("hop"), "cand", "wid", "cx", "cs", "co", "r", "mult", (F.col("back") + F.col("usual")).alias("back"), "lag", "t_seen", contribution.alias("contribution"), "w", (F.col("mult") * F.col("expected")).alias("expected"), status.alias("status")), "level")
        trace = level if trace is None else trace.unionByName(level)
        if hop < config.K:
            frontier = level.where("status = 'expanded'").join(small(heads, graph.categories), "wid").groupBy("fact_id", "cs", "co", F.col("r_head").alias("r")).agg(F.sum("mult").alias("mult"), F.min("back").alias("back"))
            frontier = frontier.withColumn("mult", F.lit(1).cast("long")) if config.dedupe else frontier
    return trace, nodes, seen


def _walk_pairs(facts: DataFrame, graph: RuleGraph, config: ScoreConfig) -> DataFrame:
    """The trace of :func:`walk` over chains where each fact carries what its pair had before it: no table and no join by fact,
    and no shuffle of facts kept by pair."""
    links, near = (small(x, graph.categories) for x in weighed_links(graph, config))
    heads = graph.patterns.select("r").distinct().select(F.xxhash64(F.lit("chain"), "r").alias("wid"), F.col("r").alias("r_head"))
    held = with_earlier(facts.select("fact_id", "s", "r", "o", "t"), config.horizon, latest=True)
    frontier, trace = nodes_of(held, graph, "s", "o", "t", "_seen").withColumn("mult", F.lit(1).cast("long")).withColumn("back", F.lit(0).cast("long")), None
    for hop in range(config.K + 1):
        own = F.get(F.filter("_seen", lambda x: F.xxhash64(F.lit("chain"), x["r"]) == F.col("wid")), F.lit(0))["t"]
        met = frontier.join(links, ["cs", "co", "r"]).withColumn("t_seen", F.when(F.col("cx") == NO_CORNER, own)).withColumn("lag", F.col("t") - F.col("t_seen")).join(near, ["cand", "lag"], "left")
        contribution = F.when(F.col("lag").isNotNull(), F.col("mult") * F.col("w") * fit_factor(config.gap)).otherwise(0.0)
        status = F.when(F.col("lag").isNotNull(), "ok").when((F.col("cx") == NO_CORNER) & F.lit(hop < config.K), "expanded").otherwise("failed")
        met = met.withColumn("status", status).withColumn("back", F.col("back") + F.col("usual"))
        level = met.select("fact_id", F.lit(hop).alias("hop"), "cand", "wid", "cx", "cs", "co", "r", "mult", "back", "lag", "t_seen", contribution.alias("contribution"), "w", (F.col("mult") * F.col("expected")).alias("expected"), "status")
        trace = level if trace is None else trace.unionByName(level)
        if hop < config.K:
            frontier = met.where("status = 'expanded'").join(small(heads, graph.categories), "wid").groupBy("s", "o", "t", "fact_id", "cs", "co", F.col("r_head").alias("r")).agg(F.sum("mult").alias("mult"), F.min("back").alias("back"), F.first("_seen").alias("_seen"))
            frontier = frontier.withColumn("mult", F.lit(1).cast("long")) if config.dedupe else frontier
    return trace


def out_edges(nodes: DataFrame, graph: RuleGraph, seen: DataFrame) -> DataFrame:
    """(fact_id, n_out): outgoing chain links whose tail happened before the fact."""
    links = graph.links.where(F.col("cx") == NO_CORNER).select("wid", "cs", "co", F.col("r").alias("r_tail"))
    own = nodes.withColumn("wid", F.xxhash64(F.lit("chain"), "r")).join(links, ["wid", "cs", "co"])
    asked = own.select("fact_id", "cs", "co", "r", "r_tail", F.xxhash64(F.lit("chain"), "r_tail").alias("wid"))
    met = asked.join(seen.where(F.col("cx") == NO_CORNER).select("fact_id", "wid"), ["fact_id", "wid"], "left_semi")
    return met.groupBy("fact_id").agg(F.count(F.lit(1)).alias("n_out"))


def score(facts: DataFrame, history: DataFrame | None, graph: RuleGraph, config: ScoreConfig | None = None, trace_path: list | None = None, seen: DataFrame | None = None) -> DataFrame:
    """Facts (fact_id, s, r, o, t) with ev_static, score_static, ev_temporal, expected, n_in, n_out, score_temporal, score_time.

    n_in counts the links that lead to the fact's patterns: where there are none, nothing is
    expected to come before it, and a missing evidence says nothing about its time.
    score_time is the expected less the found evidence a unit of weight of the patterns that links lead to (0 where
    nothing is expected and nothing found), and half a unit more where an outgoing link's tail came
    before.

    ``history`` holds what may serve as evidence (earlier ticks only count; None: the facts are their own); ``seen`` are its
    witnesses where known. Facts whose static evidence is below ``lam`` skip the walk; their
    temporal columns are null.
    """
    config = config or ScoreConfig()
    scored = static_score(facts, graph, config)
    if config.lam > 0:
        scored = staged(scored, "static")
    walked = scored.where(F.col("ev_static") >= config.lam).select("fact_id", "s", "r", "o", "t") if config.lam > 0 else facts.select("fact_id", "s", "r", "o", "t")
    trace, nodes, seen = walk(walked, history, graph, config, seen)
    if trace_path is not None:
        trace_path.append(trace)
    first = F.col("hop") == 0
    temporal = trace.groupBy("fact_id").agg(F.sum("contribution").alias("ev_temporal"), F.sum(first.cast("long")).alias("n_in"), F.sum(F.when(first, F.col("expected"))).alias("expected"))
    mass = trace.where(first).select("fact_id", "cs", "r", "co", "w").distinct().groupBy("fact_id").agg(F.sum("w").alias("_mass"))
    out = scored.join(temporal, "fact_id", "left").join(mass, "fact_id", "left")
    ran = F.col("ev_static") >= config.lam if config.lam > 0 else F.lit(True)
    out = out.withColumn("ev_temporal", F.when(ran, F.coalesce("ev_temporal", F.lit(0.0)))).withColumn("n_in", F.coalesce("n_in", F.lit(0))).withColumn("expected", F.coalesce("expected", F.lit(0.0)))
    if config.out_edge_penalty:
        out = out.join(out_edges(nodes, graph, seen), "fact_id", "left").withColumn("n_out", F.coalesce("n_out", F.lit(0)))
    else:
        out = out.withColumn("n_out", F.lit(0).cast("long"))
    late = F.when(F.col("n_out") > 0, 0.5).otherwise(0.0)
    out = out.withColumn("score_time", F.when(F.col("ev_temporal").isNotNull(), F.coalesce((F.col("expected") - F.col("ev_temporal")) / F.col("_mass"), F.lit(0.0)) + late))
    return out.drop("_mass").withColumn("score_temporal", F.try_divide(1.0 + F.col("n_out"), F.col("ev_temporal")))


def _absent(found: DataFrame, known: DataFrame) -> DataFrame:
    """Candidates (s, r, o, t, asker, n_assert, via) summed up, without what is known."""
    out = found.groupBy("s", "r", "o", "t").agg(F.sum("n_assert").alias("support"), F.countDistinct("asker").alias("asked_by"), F.array_join(F.array_sort(F.collect_set("via")), "+").alias("via"))
    out = out.join(known.select("s", "r", "o", "t").distinct(), ["s", "r", "o", "t"], "left_anti")
    return out.select(F.xxhash64("s", "r", "o", "t").alias("fact_id"), "s", "r", "o", "t", "support", "asked_by", "via")


def missing_precursors(facts: DataFrame, graph: RuleGraph, trace: DataFrame) -> DataFrame:
    """Failed chain precursors of every hop, bound to the fact's pair: due the usual lags before the fact."""
    heads = graph.patterns.select("r").distinct().select(F.xxhash64(F.lit("chain"), "r").alias("wid"), F.col("r").alias("r_head"))
    failed = trace.where((F.col("cx") == NO_CORNER) & (F.col("status") != "ok")).select("fact_id", "cand", "wid", "back").distinct()
    asked = failed.join(heads, "wid").join(graph.links.select("cand", "n_assert"), "cand").join(facts.select("fact_id", "s", "o", "t"), "fact_id")
    return asked.select("s", F.col("r_head").alias("r"), "o", (F.col("t") - F.col("back")).alias("t"), F.col("fact_id").alias("asker"), "n_assert", F.lit("precursor").alias("via"))


def missing_legs(facts: DataFrame, history: DataFrame, graph: RuleGraph, trace: DataFrame, config: ScoreConfig) -> DataFrame:
    """Failed closures of which one leg is there: the other leg, over the same corner, at the same tick."""
    failed = trace.where((F.col("hop") == 0) & (F.col("cx") != NO_CORNER) & (F.col("status") != "ok")).select("fact_id", "cand", "wid").distinct()
    legs = closure_kinds(graph.patterns.select("r").distinct())
    asked = failed.join(legs, "wid").join(graph.links.select("cand", "n_assert"), "cand").join(facts.select("fact_id", "s", "o", "t"), "fact_id")
    width = max(1, (config.horizon or 1 << 20) + config.closure_window)
    half = half_edges(history).withColumn("b", F.explode(F.array(F.floor(F.col("t") / width), F.floor(F.col("t") / width) + 1)))
    asked = asked.withColumn("b", F.floor(F.col("t") / width))
    parts = []
    for mine, here, other, there in (("s", 1, "o", 2), ("o", 2, "s", 1)):
        leg = half.select(F.col("leaf").alias(mine), F.col("corner").alias("x"), F.col("r").alias(f"r{here}"), F.col("d").alias(f"d{here}"), F.col("t").alias("t_leg"), "b")
        met = asked.join(leg, [mine, f"r{here}", f"d{here}", "b"]).where((F.col("x") != F.col(other)) & (F.col("t_leg") < F.col("t")) & (F.col("t") - F.col("t_leg") <= width))
        forward = F.col(f"d{there}") == 1  # the corner is the subject
        parts.append(met.select(F.when(forward, F.col("x")).otherwise(F.col(other)).alias("s"), F.col(f"r{there}").alias("r"), F.when(forward, F.col(other)).otherwise(F.col("x")).alias("o"), F.col("t_leg").alias("t"), F.col("fact_id").alias("asker"), "n_assert", F.lit("leg").alias("via")))
    return parts[0].unionByName(parts[1])


def missing_successors(facts: DataFrame, history: DataFrame | None, graph: RuleGraph, config: ScoreConfig, least_share: float = 0.5) -> DataFrame:
    """What links lead to and never came: tails due the usual lag after a fact (or two legs over a corner), with none in the
    pair within the link's lags.

    Only links that at least ``least_share`` of these heads are followed by, and heads whose
    time for it is over at the end of the history (None: the facts themselves, which then carry what comes after them where
    kinds are categories and links chains: facts kept by pair are not shuffled).
    """
    by_pair = history is None and graph.categories.named and not (config.closures and graph.config.closures)
    history = facts.select("s", "r", "o", "t") if history is None else history
    end = history.agg(F.max("t")).first()[0] or 0
    lags = graph.lags.groupBy("cand").agg(F.max(F.struct("cnt", (-F.col("lag")).alias("neg"))).alias("m"), F.max("lag").alias("longest")).select("cand", (-F.col("m.neg")).alias("usual"), "longest")
    links = graph.links.select("cand", "wid", "cx", "cs", "co", F.col("r").alias("r_tail"), "n_assert").join(lags, "cand")
    rels = graph.patterns.select("r").distinct()
    chain = links.where(F.col("cx") == NO_CORNER).join(rels.select(F.xxhash64(F.lit("chain"), "r").alias("wid"), F.col("r").alias("r_head")), "wid").select("cand", "cs", "co", "r_head", "r_tail", "n_assert", "usual", "longest")
    chain = small(chain, graph.categories)
    if graph.categories.named:  # a fact's only node is told by itself
        known = graph.patterns.select(F.col("cs").alias("ps"), F.col("r"), F.col("co").alias("po")).distinct()
        if by_pair:
            longest = max(1, lags.agg(F.max("longest")).first()[0] or 1)
            later = Window.partitionBy("s", "o").orderBy("t").rangeBetween(1, longest)
            facts = facts.withColumn("_later", F.collect_set(F.struct("r", "t")).over(later))
        nodes = profiled(facts, graph.categories).join(small(known, graph.categories), ["ps", "r", "po"], "left_semi").withColumnsRenamed({"ps": "cs", "po": "co"})
        found = nodes.withColumnRenamed("r", "r_head").join(chain, ["cs", "co", "r_head"])
    else:
        found = nodes_of(facts, graph).withColumnRenamed("r", "r_head").join(chain, ["cs", "co", "r_head"]).join(facts.select("fact_id", "s", "o", "t"), "fact_id")
    columns = ["cand", "s", "o", "t", "r_tail", "n_assert", "usual", "longest", F.col("fact_id").alias("asker")]
    if by_pair:
        came = F.exists("_later", lambda x: (x["r"] == F.col("r_tail")) & (x["t"] - F.col("t") <= F.col("longest")))
        asked = found.where(F.col("t") + F.col("longest") <= end).select(*columns, came.alias("came"))
        followed = asked.groupBy("cand").agg(F.count(F.lit(1)).alias("_all"), F.sum(F.col("came").cast("long")).alias("_came"))
        followed = staged(followed.where((F.col("_came") > 0) & (F.col("_came") >= least_share * F.col("_all"))), "followed")
        open_ = asked.where(~F.col("came")).join(small(followed.select("cand"), graph.categories), "cand", "left_semi")
        return open_.select("s", F.col("r_tail").alias("r"), "o", (F.col("t") + F.col("usual")).alias("t"), "asker", "n_assert", F.lit("successor").alias("via"))
    asked = found.select(*columns)
    if config.closures and graph.config.closures:
        width = max(1, config.closure_window)
        kinds = closure_kinds(rels).join(links.where(F.col("cx") != NO_CORNER), "wid")
        kinds = kinds.select("cand", "cx", "cs", "co", "r1", "d1", "r2", "d2", "r_tail", "n_assert", "usual", "longest")
        half = lambda df, i: half_edges(df).distinct().select(F.col("leaf").alias(f"e{i}"), F.col("corner").alias("x"), F.col("r").alias(f"r{i}"), F.col("d").alias(f"d{i}"), F.col("t").alias(f"t{i}"), F.floor(F.col("t") / width).alias("b"))
        one = half(facts, 1).join(kinds, ["r1", "d1"])
        two = half(in_sight(history, facts, width), 2).withColumn("b", F.explode(F.array(*[F.col("b") + k for k in (-1, 0, 1)])))
        met = one.join(two, ["x", "b", "r2", "d2"]).where((F.abs(F.col("t1") - F.col("t2")) <= width) & (F.col("e1") != F.col("e2")))
        held = graph.categories.entities.join(graph.categories.cats, "profile").select("eid", F.col("cat").cast("string").alias("c"))
        for end_, cat in (("e1", "cs"), ("e2", "co"), ("x", "cx")):
            met = met.join(held.select(F.col("eid").alias(end_), F.col("c").alias(f"_{cat}")), end_).where(F.col(f"_{cat}") == F.col(cat).cast("string")).drop(f"_{cat}")
        legs = met.select("cand", F.col("e1").alias("s"), F.col("e2").alias("o"), F.greatest("t1", "t2").alias("t"), "r_tail", "n_assert", "usual", "longest", F.xxhash64("e1", "e2", "x", "t1", "t2").alias("asker")).distinct()
        asked = asked.unionByName(legs)
    asked = staged(asked.where(F.col("t") + F.col("longest") <= end), "asked")
    width = max(1, config.horizon or 1 << 20)
    later = history.select("s", "o", F.col("r").alias("r_tail"), F.col("t").alias("t_tail")).withColumn("b", F.explode(F.array(F.floor(F.col("t_tail") / width), F.floor(F.col("t_tail") / width) - 1)))
    came = asked.withColumn("b", F.floor(F.col("t") / width)).join(later, ["s", "o", "r_tail", "b"]).where((F.col("t_tail") > F.col("t")) & (F.col("t_tail") - F.col("t") <= F.col("longest"))).select("asker", "cand").distinct()
    followed = asked.groupBy("cand").agg(F.count(F.lit(1)).alias("_all")).join(came.groupBy("cand").agg(F.count(F.lit(1)).alias("_came")), "cand").where(F.col("_came") >= least_share * F.col("_all"))
    open_ = asked.join(followed.select("cand"), "cand", "left_semi").join(came, ["asker", "cand"], "left_anti")
    return open_.select("s", F.col("r_tail").alias("r"), "o", (F.col("t") + F.col("usual")).alias("t"), "asker", "n_assert", F.lit("successor").alias("via"))


def missing_candidates(facts: DataFrame, history: DataFrame, graph: RuleGraph, trace: DataFrame, known: DataFrame | None = None, config: ScoreConfig | None = None) -> DataFrame:
    """Facts that should be there and are absent from ``known``: failed precursors, missing legs of closures, missing successors.

    support: assertions of the links that ask for it; asked_by: facts that do; via: how.
    """
    config = config or ScoreConfig(horizon=graph.config.horizon)
    found = missing_precursors(facts, graph, trace).unionByName(missing_successors(facts, history, graph, config))
    if config.closures and graph.config.closures:
        found = found.unionByName(missing_legs(facts, history, graph, trace, config))
    return _absent(found, known if known is not None else history)


def missing_score(candidates: DataFrame, history: DataFrame, graph: RuleGraph, config: ScoreConfig | None = None) -> DataFrame:
    """Candidates with both evidences and missing_score, high where both scores are low.

    Static evidence counts by its logarithm (64 for all), temporal evidence by what was expected: the mean of both.
    """
    scored = score(candidates.select("fact_id", "s", "r", "o", "t"), history, graph, config)
    level = F.least(F.lit(1.0), F.log2(1 + F.coalesce(F.col("ev_static"), F.lit(0.0))) / 64)
    scored = scored.withColumn("missing_score", (level - F.coalesce("score_time", F.lit(1.0))) / 2)
    return candidates.select("fact_id", "support", "asked_by").join(scored, "fact_id")


def classify(scored: DataFrame, th_static: float, th_temporal: float, by: str = "score_temporal") -> DataFrame:
    """Adds verdict: conceptual, time or valid, by thresholds on the scores (time by ``score_temporal`` or ``score_time``);
    no evidence exceeds any threshold."""
    over = lambda c, th: F.col(c).isNull() | (F.col(c) > th)
    verdict = F.when(over("score_static", th_static), "conceptual").when(over(by, th_temporal), "time").otherwise("valid")
    return scored.withColumn("verdict", verdict)


def fix_prompts(facts: DataFrame, graph: RuleGraph, top: int = 5) -> DataFrame:
    """Selected patterns that share two of a fact's three parts: what to change, by assertions."""
    nodes = _expanded(with_profiles(facts, graph.categories.entities).select("fact_id", "ps", "r", "po"), graph.categories).select("fact_id", "cs", "r", "co").distinct()
    patterns = graph.patterns.where("selected").select("cs", "r", "co", "n_assert")
    named = lambda change, keys: nodes.select("fact_id", *keys).distinct().join(patterns, keys).select("fact_id", F.lit(change).alias("change"), F.col("cs").cast("string"), F.col("r").cast("string"), F.col("co").cast("string"), "n_assert")
    found = named("object", ["cs", "r"]).unionByName(named("relation", ["cs", "co"])).unionByName(named("subject", ["r", "co"]))
    found = found.join(nodes.select("fact_id", F.col("cs").cast("string"), F.col("r").cast("string"), F.col("co").cast("string")), ["fact_id", "cs", "r", "co"], "left_anti")
    order = Window.partitionBy("fact_id").orderBy(F.desc("n_assert"), "change", "cs", "r", "co")
    return found.withColumn("rank", F.row_number().over(order)).where(F.col("rank") <= top)


def time_prompts(facts: DataFrame, history: DataFrame, graph: RuleGraph, config: ScoreConfig | None = None) -> DataFrame:
    """For each fact the tick (t_hint) that most links favour: witnesses of any time plus the link's usual lag vote for it,
    tails of outgoing links that would then have come before vote against it (votes in shares of the links' heads and tails)."""
    config = config or ScoreConfig()
    links, _ = weighed_links(graph, config)
    links = links.select("cand", "wid", "cx", "cs", "co", "r", "usual", (F.col("expected") / F.col("w")).alias("share"))
    nodes = nodes_of(facts, graph).join(facts.select("fact_id", "s", "o"), "fact_id")
    asked = nodes.join(links, ["cs", "co", "r"])
    own = history.join(facts.select("s", "o").distinct(), ["s", "o"], "left_semi")
    chain = chain_witnesses(own)
    kinds = linked_closures(graph.links, history) if config.closures and graph.config.closures else None
    witnesses = chain if kinds is None else chain.unionByName(closure_witnesses(history, graph.categories.entities, facts, config.closure_window, kinds=kinds))
    witnesses = witnesses.join(corner_cats(graph.categories), "corner").select("s", "o", "wid", "cx", F.col("t").alias("t_w")).distinct()
    votes = asked.join(witnesses, ["s", "o", "wid", "cx"]).groupBy("fact_id", "s", "o", (F.col("t_w") + F.col("usual")).alias("t_hint")).agg(F.sum("share").alias("votes"))
    back = graph.links.where(F.col("cx") == NO_CORNER).select("wid", "cs", "co", F.col("r").alias("r_tail"))
    against = nodes.withColumn("wid", F.xxhash64(F.lit("chain"), "r")).join(back, ["wid", "cs", "co"]).select("fact_id", "s", "o", "r_tail").distinct()
    ends = own.groupBy("s", "o", F.col("r").alias("r_tail")).agg(F.min("t").alias("first_tail"))
    against = against.join(ends, ["s", "o", "r_tail"]).select("fact_id", "first_tail")
    lost = votes.join(against, "fact_id").where("first_tail < t_hint").groupBy("fact_id", "t_hint").agg(F.count(F.lit(1)).alias("n_before"))
    net = votes.join(lost, ["fact_id", "t_hint"], "left").withColumn("net", F.col("votes") - 0.5 * F.coalesce("n_before", F.lit(0)))
    best = net.groupBy("fact_id").agg(F.max(F.struct("net", (-F.col("t_hint")).alias("neg"))).alias("m"))
    return facts.join(best.select("fact_id", (-F.col("m.neg")).alias("t_hint"), F.col("m.net").alias("votes")), "fact_id")


def explain(trace: DataFrame, names: DataFrame) -> DataFrame:
    """Readable evidence: for each fact and hop the link, its witness time and what it added."""
    return trace.join(names, "wid", "left").select("fact_id", "hop", "kind", F.col("label").alias("precursor"), F.col("cs").cast("string").alias("subject_category"), F.col("r").cast("string").alias("relation"), F.col("co").cast("string").alias("object_category"), "t_seen", "lag", "contribution", "status")
