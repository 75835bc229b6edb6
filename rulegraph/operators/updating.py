"""Keeping a rule graph current: new facts, categories, patterns, links and lags; when to rebuild."""

from __future__ import annotations

from dataclasses import dataclass, replace

from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from ..functions.mdl import code_bits, error_bits
from ..plans.build import RuleGraph, _expanded, _spread_tails, link_candidates, link_key, profiled, small, with_profiles
from ..storage import staged
from .categories import Categories
from .occurrences import NO_CORNER, all_witnesses, chain_witnesses, closure_witnesses, earlier_chains, latest_witnesses, linked_closures
from .scoring import in_sight
from .selection import choose_small, rank_candidates, saving_alone, select_passes


@dataclass(frozen=True)
class OnlineConfig:
    """``refresh``: error, every_n_ticks, every_n_facts or never; ``monitor``: cumulative (as printed) or per_slice;
    ``th_temporal`` is a bound on the score that ``time_by`` names. Without the updater graph and history stay as they are.
    ``looks``: how often a batch is judged, each time resting on what the look before held valid of it; None: until no verdict
    changes, which is what one batch a tick would give."""

    updater: bool = True
    refresh: str = "error"
    refresh_every: int = 30
    monitor: str = "cumulative"
    th_static: float = 1e-3
    th_temporal: float = 1.0
    time_by: str = "score_time"
    looks: int | None = 2


def append_facts(history: DataFrame, batch: DataFrame) -> DataFrame:
    """History with the facts of the batch that it lacks."""
    return history.unionByName(batch.select("s", "r", "o", "t").distinct().join(history.select("s", "r", "o", "t"), ["s", "r", "o", "t"], "left_anti"))


def extend_categories(graph: RuleGraph, history: DataFrame, batch: DataFrame) -> Categories:
    """Entities of the batch with a relation that they did not have get the largest combination that holds it.

    A new entity has only new relations, so it gets categories the same way. Profiles stay
    the unit of storage: a changed entity moves to a profile of its old one and the
    categories added.
    """
    combos = graph.categories.combos
    if combos is None:
        ends = batch.select(F.col("s").alias("eid")).unionByName(batch.select(F.col("o").alias("eid"))).distinct()
        fresh = ends.join(graph.categories.entities, "eid", "left_anti").select("eid", F.substring("eid", 1, 1).alias("profile"))
        return replace(graph.categories, entities=graph.categories.entities.unionByName(fresh))
    pair = lambda df: df.select(F.col("s").alias("eid"), "r").unionByName(df.select(F.col("o").alias("eid"), "r")).distinct()
    touched = pair(batch)
    held = pair(history.join(touched.select(F.col("eid").alias("s")).distinct(), "s", "left_semi").select("s", "r", "o")).unionByName(pair(history.join(touched.select(F.col("eid").alias("o")).distinct(), "o", "left_semi").select("s", "r", "o"))).distinct()
    new = touched.join(held, ["eid", "r"], "left_anti")
    largest = combos.select("cat", "n_ent", F.explode("rels").alias("r")).groupBy("r").agg(F.max(F.struct("n_ent", "cat")).alias("m")).select("r", F.col("m.cat").alias("cat"))
    added = staged(new.join(largest, "r").groupBy("eid").agg(F.sort_array(F.collect_set("cat")).alias("added")), "added")
    moved = added.join(graph.categories.entities, "eid", "left")
    moved = moved.select("eid", "profile", "added", F.xxhash64(F.coalesce("profile", F.lit(0)), "added").alias("fresh"))
    entities = graph.categories.entities.join(moved.select("eid"), "eid", "left_anti").unionByName(moved.select("eid", F.col("fresh").alias("profile")))
    kinds = moved.select("profile", "added", "fresh").distinct()
    inherited = kinds.join(graph.categories.cats, "profile").select(F.col("fresh").alias("profile"), "cat")
    own = kinds.select(F.col("fresh").alias("profile"), F.explode("added").alias("cat"))
    cats = graph.categories.cats.unionByName(inherited).unionByName(own).distinct()
    return Categories(staged(entities, "entities"), staged(cats, "cats"), combos)


def extend_patterns(graph: RuleGraph, categories: Categories, batch: DataFrame) -> DataFrame:
    """Patterns with those of the batch added that shorten the description on the batch's ticks, and counts kept up.

    What known patterns explain already counts for nothing: candidates are ranked and taken in
    passes over the facts left open, as in building.
    """
    facts = batch.select("s", "r", "o", "t")
    cells = staged(with_profiles(facts, categories.entities).groupBy("ps", "r", "po", "t").agg(F.count(F.lit(1)).alias("n")), "cells")
    spread = staged(_expanded(cells.select("ps", "r", "po").distinct(), categories), "spread")
    known = graph.patterns.where("selected").select("cs", "r", "co")
    mapped = spread.join(known, ["cs", "r", "co"], "left_semi").select("ps", "r", "po").distinct()
    ticks = facts.groupBy("t").agg(F.count(F.lit(1)).alias("n_t")).join(cells.join(mapped, ["ps", "r", "po"], "left_semi").groupBy("t").agg(F.sum("n").alias("m0")), "t", "left").fillna(0, ["m0"])
    seen = cells.join(spread, ["ps", "r", "po"]).groupBy("cs", "r", "co").agg(F.sum("n").alias("_more"))
    kept = graph.patterns.join(seen, ["cs", "r", "co"], "left").select("cand", "cs", "r", "co", (F.col("n_assert") + F.coalesce("_more", F.lit(0))).alias("n_assert"), "selected")
    open_ = cells.join(mapped, ["ps", "r", "po"], "left_anti")
    cover = staged(open_.join(spread, ["ps", "r", "po"]).select(F.xxhash64("cs", "r", "co").alias("cand"), "cs", "r", "co", F.xxhash64("ps", "r", "po").alias("cell"), "t", "n"), "cover")
    if cover.isEmpty():
        return kept
    space = float(graph.scalars["space"])
    n_facts, n_cat = float(max(1, graph.scalars["n_facts"])), float(max(1, graph.scalars["n_categories"]))
    n_ent = float(max(1, graph.scalars["n_entities"]))
    counts = cover.groupBy("cand", "cs", "r", "co").agg(F.sum("n").alias("n_assert"))
    size = categories.entities.groupBy("profile").agg(F.count(F.lit(1)).alias("n")).join(categories.cats, "profile").groupBy("cat").agg(F.sum("n").alias("n"))
    costed = counts.join(size.select(F.col("cat").alias("cs"), F.col("n").alias("n_cs")), "cs").join(size.select(F.col("cat").alias("co"), F.col("n").alias("n_co")), "co")
    cost = F.log2(F.lit(n_cat)) + code_bits("n_cs", F.lit(n_ent)) + code_bits("n_co", F.lit(n_ent)) + code_bits("n_assert", F.lit(n_facts)) + 1
    if graph.config.criterion != "errors":
        cost = cost + 2 * F.col("n_assert") * F.log2(F.col("n_assert").cast("double"))
    own = cover.select("cand", "cell", "t", "n")
    costed = staged(costed.withColumn("bits", cost), "costed")
    found = choose_small(costed, own, ticks, space, graph.config.rank_by, graph.config.passes)
    if found is None:
        ranked = staged(rank_candidates(costed.join(saving_alone(own, ticks, space), "cand"), graph.config.rank_by), "ranked")
        taken, _ = select_passes(ranked.select("cand", "rank", "bits"), own, ticks, space, graph.config.passes)
        chosen = ranked.join(taken.select("cand"), "cand", "left_semi")
    else:
        chosen = found[0].where("selected")
    fresh = chosen.select("cand", "cs", "r", "co", "n_assert", F.lit(True).alias("selected"))
    # a pattern kept for time checks only becomes a selected one when it pays
    return kept.join(fresh.select("cs", "r", "co"), ["cs", "r", "co"], "left_anti").select(*fresh.columns).unionByName(fresh)


def extend_links(graph: RuleGraph, categories: Categories, patterns: DataFrame, history: DataFrame, batch: DataFrame, window: int) -> tuple[DataFrame, DataFrame]:
    """Chain links into new patterns from facts of the pair at most window ticks earlier, and the counts and lags of all links that the batch follows."""
    facts = batch.select(F.xxhash64("s", "r", "o", "t").alias("fact_id"), "s", "r", "o", "t").dropDuplicates(["fact_id"])
    past = in_sight(history, facts, window + graph.config.L).select("s", "r", "o", "t").unionByName(facts.select("s", "r", "o", "t"))
    witnesses = chain_witnesses(past.join(facts.select("s", "o").distinct(), ["s", "o"], "left_semi"))
    kinds = linked_closures(graph.links, past) if graph.config.closures else None
    if kinds is not None:  # closures only add to links that are there
        witnesses = witnesses.unionByName(closure_witnesses(past, categories.entities, facts, graph.config.L, window, kinds))
    seen = (all_witnesses if graph.config.heads == "all" else latest_witnesses)(facts, witnesses, window)
    tails = staged(with_profiles(facts, categories.entities).select("fact_id", "ps", "r", "po", "t").join(seen, "fact_id"), "tails")
    found, lags = link_candidates(tails, categories, graph.config.max_links)
    once = tails.select("fact_id", "ps", "r", "po", "wid", "corner").distinct().groupBy("ps", "r", "po", "wid", "corner").agg(F.count(F.lit(1)).alias("n"))
    covered = _spread_tails(once, categories).groupBy(link_key()).agg(F.sum("n").alias("_cover"))
    found = found.join(covered, "cand")
    fresh_patterns = patterns.join(graph.patterns.where("selected"), ["cs", "r", "co"], "left_anti").select("cs", "r", "co")
    fresh = found.where(F.col("cx") == NO_CORNER).join(fresh_patterns, ["cs", "r", "co"], "left_semi").join(graph.links.select("cand"), "cand", "left_anti")
    old = graph.links.select("cand", "wid", "cx", "cs", "co", "r", "n_assert", "n_cover").join(found.select("cand", F.col("n_assert").alias("_more"), "_cover"), "cand", "left")
    old = old.select("cand", "wid", "cx", "cs", "co", "r", (F.col("n_assert") + F.coalesce("_more", F.lit(0))).alias("n_assert"), (F.col("n_cover") + F.coalesce("_cover", F.lit(0))).alias("n_cover"))
    links = old.unionByName(fresh.select("cand", "wid", "cx", "cs", "co", "r", "n_assert", F.col("_cover").alias("n_cover")))
    merged = graph.lags.select("cand", "lag", "cnt").unionByName(lags.join(links.select("cand"), "cand", "left_semi").select("cand", "lag", "cnt"))
    return links, merged.groupBy("cand", "lag").agg(F.sum("cnt").alias("cnt"))


def explained_ticks(facts: DataFrame, history: DataFrame | None, graph: RuleGraph, horizon: int | None) -> DataFrame:
    """(t, n_facts, n_explained, error_bits) of facts: explained if mapped and led to by a link's earlier witness, as in building.

    Without a history the facts are a set and their own one.
    """
    if history is None and horizon is not None and not graph.config.closures:
        return _priced_ticks(_led_chains(facts, graph, horizon), graph)
    history = facts if history is None else history
    keyed = facts.select(F.xxhash64("s", "r", "o", "t").alias("fact_id"), "s", "r", "o", "t").dropDuplicates(["fact_id"])
    past = in_sight(history, keyed, None if horizon is None else horizon + graph.config.L).select("s", "r", "o", "t").unionByName(keyed.select("s", "r", "o", "t"))
    witnesses = chain_witnesses(past.join(keyed.select("s", "o").distinct(), ["s", "o"], "left_semi"))
    kinds = linked_closures(graph.links, past) if graph.config.closures else None
    if kinds is not None:
        witnesses = witnesses.unionByName(closure_witnesses(past, graph.categories.entities, keyed, graph.config.L, horizon, kinds))
    seen = latest_witnesses(keyed, witnesses, horizon)
    cells = profiled(keyed, graph.categories).select("fact_id", "ps", "r", "po")
    mapped = _expanded(cells.select("ps", "r", "po").distinct(), graph.categories).join(graph.patterns.select("cs", "r", "co"), ["cs", "r", "co"], "left_semi").select("ps", "r", "po").distinct()
    tails = cells.join(mapped, ["ps", "r", "po"], "left_semi").join(seen, "fact_id")
    kinds = _spread_tails(tails.select("ps", "r", "po", "wid", "corner").distinct(), graph.categories).join(graph.links.select("wid", "cx", "cs", "co", "r"), ["wid", "cx", "cs", "co", "r"], "left_semi").select("ps", "r", "po", "wid", "corner").distinct()
    led = tails.join(kinds, ["ps", "r", "po", "wid", "corner"], "left_semi").select("fact_id").distinct()
    return _priced_ticks(keyed.join(led.withColumn("e", F.lit(1)), "fact_id", "left").groupBy("t").agg(F.count(F.lit(1)).alias("n_facts"), F.count("e").alias("n_explained")), graph)


def _led_chains(facts: DataFrame, graph: RuleGraph, horizon: int) -> DataFrame:
    """(t, n_facts, n_explained) by chains among the facts themselves: one shuffle of the facts, then counts."""
    own = profiled(facts.select("s", "r", "o", "t"), graph.categories).select("s", "o", "ps", "r", "po", "t")
    cells = own.select("ps", "r", "po").distinct()
    mapped = _expanded(cells, graph.categories).join(graph.patterns.select("cs", "r", "co"), ["cs", "r", "co"], "left_semi").select("ps", "r", "po").distinct()
    tails = earlier_chains(own, horizon)
    chains = graph.links.where(F.col("cx") == NO_CORNER).select("wid", "cs", "co", "r")
    kinds = _expanded(mapped, graph.categories).join(chains, ["cs", "co", "r"]).select("ps", "r", "po", "wid").distinct()
    led = tails.join(small(kinds, graph.categories), ["ps", "r", "po", "wid"], "left_semi").select("s", "r", "o", "t").distinct()
    explained = led.groupBy("t").agg(F.count(F.lit(1)).alias("n_explained"))
    return facts.groupBy("t").agg(F.count(F.lit(1)).alias("n_facts")).join(explained, "t", "left").fillna(0, ["n_explained"])


def _priced_ticks(ticks: DataFrame, graph: RuleGraph) -> DataFrame:
    return ticks.withColumn("error_bits", error_bits(float(graph.scalars["space"]), "n_explained", F.col("n_facts") - F.col("n_explained")))


def should_refresh(online: dict, offline: dict, config: OnlineConfig) -> bool:
    """``online``/``offline``: bits, ticks (and facts) so far. The error rule compares sums as printed, or means a tick."""
    if config.refresh == "never":
        return False
    if config.refresh == "every_n_ticks":
        return online["ticks"] >= config.refresh_every
    if config.refresh == "every_n_facts":
        return online["facts"] >= config.refresh_every
    if config.monitor == "per_slice":
        return online["bits"] / max(1, online["ticks"]) > offline["bits"] / max(1, offline["ticks"])
    return online["bits"] > offline["bits"]


def update(graph: RuleGraph, history: DataFrame, batch: DataFrame) -> tuple[RuleGraph, DataFrame]:
    """(graph, history) after valid facts arrived. Patterns, links and categories only ever grow."""
    window = graph.config.horizon if graph.config.horizon is not None else graph.config.L
    categories = extend_categories(graph, history, batch)
    patterns = staged(extend_patterns(graph, categories, batch), "patterns")
    links, lags = extend_links(graph, categories, patterns, history, batch, window)
    fresh = replace_graph(graph, categories, patterns, staged(links, "links"), staged(lags, "lags"))
    return fresh, append_facts(history, batch)


def replace_graph(graph: RuleGraph, categories, patterns, links, lags) -> RuleGraph:
    return RuleGraph(categories, patterns, links, lags, graph.slices, dict(graph.scalars), graph.config)


__all__ = ["NO_CORNER", "OnlineConfig", "append_facts", "explained_ticks", "extend_categories", "extend_links", "extend_patterns", "link_key", "should_refresh", "update"]
