"""Building a rule graph: categories, candidates, ranking and selection by description length."""

from __future__ import annotations

import json
from collections.abc import Callable
from concurrent.futures import Future
from dataclasses import asdict, dataclass, field, replace

import numpy as np
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from ..functions.mdl import code_bits, error_bits, header_bits
from ..operators import categories as cats
from ..operators.occurrences import NO_CORNER, all_witnesses, chain_witnesses, closure_witnesses, earlier_chains, earlier_closures, latest_witnesses
from ..operators.selection import choose_small, entropy_bits, rank_candidates, saving_alone, select_passes
from ..storage import staged, staged_parts


@dataclass(frozen=True)
class BuildConfig:
    """``L``: ticks between the two legs of a closure; ``horizon``: ticks a witness stays of interest (None: ever).

    ``heads``: link assertions pair a fact with ``all`` earlier witnesses in the horizon or with the
    ``latest`` of each kind. ``assertion_cost``: ``conditional`` or ``printed``. ``criterion``: the error bits that a
    candidate saves must exceed its bits of model and assertions (``total``), of assertions (``data``), or of the model
    (``errors``: where entities are so many and so even that naming them in a pattern costs what an error costs). ``passes``: at most so many over
    the candidates; None until a pass adds nothing. ``max_links``: only the most asserted candidate links; None: all of them.
    """

    categories: cats.CategoryConfig = field(default_factory=cats.CategoryConfig)
    kinds_known: bool = False
    L: int = 5
    horizon: int | None = None
    closures: bool = True
    max_links: int | None = None
    rank_by: str = "error_reduction"
    criterion: str = "total"
    assertion_cost: str = "conditional"
    passes: int | None = None
    heads: str = "all"


@dataclass
class RuleGraph:
    """A model: categories, patterns (cs, r, co), links (wid, cx, cs, co, r), lags and scalars."""

    categories: cats.Categories
    patterns: DataFrame
    links: DataFrame
    lags: DataFrame
    slices: DataFrame
    scalars: dict
    config: BuildConfig
    #: Small tables worked out from the graph (weights and fits of links), by score settings.
    memo: dict = field(default_factory=dict, compare=False, repr=False)

    def save(self, path: str) -> None:
        """One folder a version; the scalars are written last and mark it complete."""
        for name in ("patterns", "links", "lags", "slices"):
            getattr(self, name).write.mode("overwrite").parquet(f"{path}/{name}")
        self.categories.entities.write.mode("overwrite").parquet(f"{path}/entities")
        self.categories.cats.write.mode("overwrite").parquet(f"{path}/cats")
        spark = self.patterns.sparkSession
        spark.createDataFrame([(json.dumps({"scalars": self.scalars, "config": asdict(self.config)}),)], "value string").coalesce(1).write.mode("overwrite").text(f"{path}/scalars")

    @staticmethod
    def load(spark: SparkSession, path: str) -> RuleGraph:
        held = json.loads(spark.read.text(f"{path}/scalars").first()[0])
        config = held["config"]
        config["categories"] = cats.CategoryConfig(**config["categories"])
        frames = {name: spark.read.parquet(f"{path}/{name}") for name in ("patterns", "links", "lags", "slices", "entities", "cats")}
        return RuleGraph(cats.Categories(frames["entities"], frames["cats"]), *(frames[x] for x in ("patterns", "links", "lags", "slices")), held["scalars"], BuildConfig(**config))


def with_profiles(facts: DataFrame, entities: DataFrame, how: str = "inner") -> DataFrame:
    """Facts with the profiles of both ends (ps, po)."""
    left = entities.select(F.col("eid").alias("s"), F.col("profile").alias("ps"))
    right = entities.select(F.col("eid").alias("o"), F.col("profile").alias("po"))
    return facts.join(left, "s", how).join(right, "o", how)


def profiled(facts: DataFrame, categories: cats.Categories, how: str = "inner") -> DataFrame:
    """The same by categories: where names tell profiles, without a join."""
    if categories.named:
        return facts.select("*", F.substring("s", 1, 1).alias("ps"), F.substring("o", 1, 1).alias("po"))
    return with_profiles(facts, categories.entities, how)


def small(df: DataFrame, categories: cats.Categories) -> DataFrame:
    """A table over kinds and relations: sent to every task where kinds are few by definition, else joined as planned."""
    return F.broadcast(df) if categories.named else df


def map_patterns(facts: DataFrame, categories: cats.Categories) -> DataFrame:
    """Every fact with every pattern it maps to: subject categories times object categories."""
    held = profiled(facts, categories)
    cs = categories.cats.select(F.col("profile").alias("ps"), F.col("cat").alias("cs"))
    co = categories.cats.select(F.col("profile").alias("po"), F.col("cat").alias("co"))
    return held.join(cs, "ps").join(co, "po").drop("ps", "po")


def _expanded(cells: DataFrame, categories: cats.Categories) -> DataFrame:
    """Cells (ps, r, po, ...) with all categories of both ends."""
    cs = categories.cats.select(F.col("profile").alias("ps"), F.col("cat").alias("cs"))
    co = categories.cats.select(F.col("profile").alias("po"), F.col("cat").alias("co"))
    return cells.join(cs, "ps").join(co, "po")


def pattern_counts(facts: DataFrame, categories: cats.Categories) -> DataFrame:
    """(cs, r, co, n_assert), counted over profile pairs first: facts expand only after the aggregate."""
    cells = profiled(facts, categories).groupBy("ps", "r", "po").agg(F.count(F.lit(1)).alias("n"))
    return _expanded(cells, categories).groupBy("cs", "r", "co").agg(F.sum("n").alias("n_assert"))


@dataclass
class Sizes:
    """Entities by profile (profile, n) and facts by relation (r, n_r), with their sums."""

    profiles: DataFrame
    relations: DataFrame
    n_ent: int
    n_facts: int
    n_rel: int


def sizes_of(entities: DataFrame, facts: DataFrame, n: str | None = None) -> Sizes:
    """``n``: the column that says how many facts a row of ``facts`` stands for."""
    profiles = staged(entities.groupBy("profile").agg(F.count(F.lit(1)).alias("n")), "sizes")
    relations = staged(facts.groupBy("r").agg((F.sum(n) if n else F.count(F.lit(1))).alias("n_r")), "relations")
    total = relations.agg(F.coalesce(F.sum("n_r"), F.lit(0)), F.count(F.lit(1))).first()
    return Sizes(profiles, relations, profiles.agg(F.coalesce(F.sum("n"), F.lit(0))).first()[0], total[0], total[1])


def pattern_model_bits(patterns: DataFrame, facts: DataFrame, categories: cats.Categories, sizes: Sizes | None = None) -> DataFrame:
    """Adds bits_model: category alphabet, codes of both categories and the relation, and its direction."""
    own = sizes or sizes_of(categories.entities, facts)
    by_cat = own.profiles.join(categories.cats, "profile").groupBy("cat").agg(F.sum("n").alias("n"))
    n_cat = categories.cats.select("cat").distinct().count()
    out = patterns.join(by_cat.select(F.col("cat").alias("cs"), F.col("n").alias("n_cs")), "cs").join(by_cat.select(F.col("cat").alias("co"), F.col("n").alias("n_co")), "co").join(own.relations, "r")
    bits = F.log2(F.lit(float(max(1, n_cat)))) + code_bits("n_cs", F.lit(float(own.n_ent))) + code_bits("n_co", F.lit(float(own.n_ent))) + code_bits("n_r", F.lit(float(own.n_facts))) + 1
    return out.withColumn("bits_model", bits).drop("n_cs", "n_co", "n_r")


#: Ends of a fact with their own profile and that of the other end.
_ENDS = {"s": ("ps", "po"), "o": ("po", "ps")}


def end_vectors(held: DataFrame, end: str) -> DataFrame:
    """(profile, r, parts, m): how many entities have facts of a relation with so many (n) of each profile at the other end.

    Entities alike in this code alike in every pattern, so they are told apart only until they are counted.
    """
    mine, other = _ENDS[end]
    counts = held.groupBy("ps", "r", "po", end).agg(F.count(F.lit(1)).alias("n"))
    alike = counts.groupBy(F.col(mine).alias("profile"), "r", end).agg(F.sort_array(F.collect_list(F.struct(F.col(other).alias("other"), "n"))).alias("parts"))
    return alike.groupBy("profile", "r", "parts").agg(F.count(F.lit(1)).alias("m"))


def pattern_data_bits(facts: DataFrame, categories: cats.Categories, vectors: dict[str, DataFrame] | None = None) -> DataFrame:
    """(cand, bits_data): codes of subjects and objects among a pattern's assertions; ``vectors`` are those of both ends."""
    if vectors is None:
        held = profiled(facts, categories)
        vectors = {end: end_vectors(held, end) for end in _ENDS}
    ends = []
    for end, (mine, other) in {"s": ("cs", "co"), "o": ("co", "cs")}.items():
        rows = vectors[end].select(F.xxhash64("profile", "r", "parts").alias("vector"), "profile", "r", "m", F.explode("parts").alias("p")).select("vector", "profile", "r", "m", "p.other", "p.n")
        rows = rows.join(categories.cats.select(F.col("profile").alias("other"), F.col("cat").alias(other)), "other").groupBy("vector", "profile", "r", "m", other).agg(F.sum("n").alias("n"))
        rows = rows.join(categories.cats.select("profile", F.col("cat").alias(mine)), "profile").select(F.xxhash64("cs", "r", "co").alias("cand"), "n", "m")
        ends.append(entropy_bits(rows, "cand", weight="m").withColumnRenamed("bits", f"bits_{end}"))
    return ends[0].join(ends[1], "cand").select("cand", (F.col("bits_s") + F.col("bits_o")).alias("bits_data"))


def _price(config: BuildConfig):
    """What a candidate must save."""
    return {"total": F.col("bits_model") + F.col("bits_data"), "data": F.col("bits_data"), "errors": F.col("bits_model")}[config.criterion]


def _select(candidates: DataFrame, cover: DataFrame, ticks: DataFrame, space: float, config: BuildConfig, bits_given=None, bits_held=None) -> tuple[DataFrame, bool]:
    """Ranked candidates with saving, n_cover, rank, gain and selected, and whether the passes converged.

    ``bits_given`` and ``bits_held`` give bits anew for the set chosen so far, to the cluster and to the driver.
    """
    found = choose_small(candidates, cover, ticks, space, config.rank_by, config.passes, bits_held)
    if found is not None:
        return found
    saved = candidates.join(saving_alone(cover, ticks, space), "cand", "left").fillna({"saving": 0.0, "n_cover": 0})
    ranked = staged(rank_candidates(saved, config.rank_by), "ranked")
    taken, converged = select_passes(ranked.select("cand", "rank", "bits", *(["bits_data"] if bits_given else [])), cover, ticks, space, config.passes, bits_given)
    return ranked.join(taken.withColumn("selected", F.lit(True)), "cand", "left").withColumn("selected", F.coalesce("selected", F.lit(False))), converged


@dataclass
class Occurrences:
    """What building needs before categories are chosen: builds that differ later share one.

    ``held``: facts with profiles of both ends; ``seen``: (fact_id, pair, ps, r, po, t, seen), with all (wid, corner, t_seen)
    before a fact, None until looked for; ``memo`` and ``told``: what is made once from facts, and from what they have seen.
    """

    facts: DataFrame
    entities: DataFrame
    ticks: DataFrame
    held: DataFrame
    seen: DataFrame | None
    memo: dict = field(default_factory=dict, compare=False, repr=False)
    told: dict = field(default_factory=dict, compare=False, repr=False)


def once(memo: dict, key, make: Callable):
    """What ``make`` gives, made by whoever asks first; others wait for it."""
    mine = Future()
    held = memo.setdefault(key, mine)
    if held is mine:
        try:
            mine.set_result(make())
        except BaseException as error:
            memo.pop(key, None)
            mine.set_exception(error)
    return held.result()


def prepare(facts: DataFrame, config: BuildConfig, witness_facts: DataFrame | None = None) -> Occurrences:
    """Profiles and witnesses of facts (s, r, o, t).

    ``witness_facts`` replaces facts where witnesses are looked for (duration facts use
    another of their two times there).
    """
    return with_witnesses(profiles_and_ticks(facts, config), config, witness_facts)


def profiles_and_ticks(facts: DataFrame, config: BuildConfig, entities: DataFrame | None = None) -> Occurrences:
    """Facts with profiles, without witnesses; ``entities`` are the profiles where facts of the same triples gave them already."""
    known = lambda df: df.select(F.xxhash64("s", "r", "o", "t").alias("fact_id"), *df.columns)  # noqa: E731  (told by the rest: not written)
    facts = known(staged(facts.select("s", "r", "o", "t"), "facts"))
    if entities is None:
        entities = cats.by_kind(facts).entities if config.kinds_known else staged(cats.entity_profiles(cats.entity_relations(facts, config.categories.roles)), "entities")
    ticks = staged(facts.groupBy("t").agg(F.count(F.lit(1)).alias("n_t")), "ticks")
    held = known(staged(with_profiles(facts.drop("fact_id"), entities.select("eid", "profile")), "held"))
    return Occurrences(facts, entities, ticks, held, None)


#: So many facts or a few more ask for what came before them at once; the shuffles of one part are gone before the next one's.
FACTS_AT_ONCE = 2_000_000


def _spans(ticks: DataFrame, width: int) -> list[tuple[int | None, int | None]]:
    """Consecutive spans [low, high) of ticks with about ``FACTS_AT_ONCE`` facts each, in whole blocks of ``width`` ticks; None: open."""
    blocks = ticks.groupBy(F.floor(F.col("t") / width).cast("long").alias("b")).agg(F.sum("n_t").alias("n")).orderBy("b").collect()
    bounds, n = [None], 0
    for row in blocks:
        if n >= FACTS_AT_ONCE:
            bounds, n = [*bounds, row["b"] * width], 0
        n += row["n"]
    return list(zip(bounds, [*bounds[1:], None], strict=True))


def _found(held: DataFrame, config: BuildConfig, low: int | None, high: int | None) -> DataFrame:
    """What facts of a span of ticks saw before them: earlier facts are read as far back as they can be seen."""
    width = config.horizon + config.L
    held = held if low is None else held.where(F.col("t") >= low - width)
    held = held if high is None else held.where(F.col("t") < high)
    keyed = held.select("fact_id", F.xxhash64("s", "o").alias("pair"), "ps", "r", "po", "t", "s", "o")
    found = earlier_chains(keyed, config.horizon).select(*_SEEN)
    found = found if low is None else found.where(F.col("t") >= low)
    return found.unionByName(earlier_closures(held, config.L, config.horizon, low)) if config.closures else found


_SEEN = ("fact_id", "pair", "ps", "r", "po", "t", "wid", "corner", "t_seen")


def with_witnesses(own: Occurrences, config: BuildConfig, witness_facts: DataFrame | None = None) -> Occurrences:
    """The same with what facts have seen, by witnesses among ``witness_facts`` (by default the facts)."""
    if config.heads == "all" and config.horizon is not None and witness_facts is None:
        parts = [_found(own.held, config, *span) for span in _spans(own.ticks, max(1, config.horizon + config.L))]
    else:
        keyed = own.held.select("fact_id", F.xxhash64("s", "o").alias("pair"), "ps", "r", "po", "t", "s", "o")
        source = own.facts if witness_facts is None else witness_facts
        witnesses = chain_witnesses(source)
        if config.closures:
            witnesses = witnesses.unionByName(closure_witnesses(source, own.entities, own.facts, config.L, config.horizon))
        seen = (all_witnesses if config.heads == "all" else latest_witnesses)(own.facts, witnesses, config.horizon)
        parts = [keyed.join(seen, "fact_id").select(*_SEEN)]
    parts = [x.groupBy("fact_id", "pair", "ps", "r", "po", "t").agg(F.collect_set(F.struct("wid", "corner", "t_seen")).alias("seen")) for x in parts]
    return replace(own, seen=staged_parts(parts, "seen"), told={})


@dataclass
class FactTables:
    """Small tables of facts that no category changes: (ps, r, po, t, n, cell), the vectors of both ends, and sizes."""

    cells: DataFrame
    vectors: dict[str, DataFrame]
    sizes: Sizes


def fact_tables(own: Occurrences) -> FactTables:
    from .workloads import together

    def counted() -> tuple[DataFrame, Sizes]:
        cells = staged(own.held.groupBy("ps", "r", "po", "t").agg(F.count(F.lit(1)).alias("n")).withColumn("cell", F.xxhash64("ps", "r", "po")), "cells")
        return cells, sizes_of(own.entities, cells, "n")

    def make() -> FactTables:
        (cells, sizes), *ends = together([counted, *[lambda e=e: staged(end_vectors(own.held, e), "vectors") for e in _ENDS]])
        return FactTables(cells, dict(zip(_ENDS, ends, strict=True)), sizes)

    return once(own.memo, "tables", make)


@dataclass
class TailTables:
    """Small tables of what facts have seen that no category changes: tails by lag (ps, r, po, wid, corner, lag, n), bits of
    picking among what was seen (ps, r, po, wid, corner, b), and groups of facts that saw the same (cell, ps, r, po, t, n, wid, corner)."""

    lags: DataFrame
    picks: DataFrame
    cells: DataFrame


def tails_of(own: Occurrences, closures: bool) -> DataFrame:
    """(fact_id, pair, ps, r, po, t, wid, corner, lag, t_seen)."""
    rows = own.seen.select("fact_id", "pair", "ps", "r", "po", "t", F.explode("seen").alias("_x")).select("fact_id", "pair", "ps", "r", "po", "t", "_x.wid", "_x.corner", (F.col("t") - F.col("_x.t_seen")).alias("lag"), "_x.t_seen")
    return rows if closures else rows.where(F.col("corner") == NO_CORNER)


def tail_tables(own: Occurrences, closures: bool) -> TailTables:
    from .workloads import together

    def grouped() -> tuple[DataFrame, DataFrame]:
        kinds = F.sort_array(F.transform("seen", lambda x: F.struct(x["wid"].alias("wid"), x["corner"].alias("corner"))))
        kinds = kinds if closures else F.filter(kinds, lambda x: x["corner"] == NO_CORNER)
        groups = own.seen.select("ps", "r", "po", "t", kinds.alias("kinds")).where(F.size("kinds") > 0)
        groups = staged(groups.groupBy("ps", "r", "po", "kinds", "t").agg(F.count(F.lit(1)).alias("n")), "groups")
        bits = (F.col("n") * F.log2(F.size("kinds").cast("double"))).alias("b")
        picks = groups.select("ps", "r", "po", bits, F.explode("kinds").alias("k")).groupBy("ps", "r", "po", "k.wid", "k.corner").agg(F.sum("b").alias("b"))
        cells = groups.groupBy("ps", "r", "po", F.array_distinct("kinds").alias("before"), "t").agg(F.sum("n").alias("n"))
        cells = cells.select(F.xxhash64("ps", "r", "po", "before").alias("cell"), "ps", "r", "po", "t", "n", F.explode("before").alias("k")).select("cell", "ps", "r", "po", "t", "n", "k.wid", "k.corner")
        return tuple(together([lambda: staged(picks, "picks"), lambda: staged(cells, "cells")]))

    def make() -> TailTables:
        lags, (picks, cells) = together([lambda: staged(lag_counts(tails_of(own, closures)), "lags"), grouped])
        return TailTables(lags, picks, cells)

    return once(own.told, closures, make)


@dataclass
class ChosenPatterns:
    """Categories, all candidate patterns with what was selected, whether the passes converged, and counts."""

    categories: cats.Categories
    patterns: DataFrame
    settled: bool
    n_rel: int
    n_facts: int
    n_ent: int
    n_cat: int

    @property
    def space(self) -> float:
        return float(self.n_ent) ** 2 * self.n_rel


def ready(facts: DataFrame, config: BuildConfig) -> Occurrences:
    """The same as :func:`prepare`, with all tables that builds from it share."""
    from .workloads import together

    own = profiles_and_ticks(facts, config)

    def led() -> Occurrences:
        found = with_witnesses(own, config)
        tail_tables(found, config.closures)
        return found

    jobs = [lambda: fact_tables(own), *([] if config.kinds_known else [lambda: begun(own, config)])]
    return together([led, *jobs])[0]


def categories_of(own: Occurrences, config: BuildConfig, categories: cats.Categories | None = None) -> cats.Categories:
    """Categories by the settings; ``categories`` where facts of the same triples gave them already."""

    def make() -> cats.Categories:
        if categories is not None:
            return categories
        if config.kinds_known:
            return cats.by_kind(own.facts)
        return cats.learn(own.facts, config.categories, own.entities, begun(own, config))

    return once(own.memo, ("categories", config.categories, config.kinds_known), make)


def begun(own: Occurrences, config: BuildConfig) -> cats.Combos:
    """Frequent combinations, for all numbers of categories."""
    return once(own.memo, ("combos", replace(config.categories, k=0)), lambda: cats.frequent(own.entities, config.categories))


def choose_patterns(own: Occurrences, config: BuildConfig, categories: cats.Categories | None = None) -> ChosenPatterns:
    """The part of a build that needs no witnesses; ``categories`` where facts of the same triples gave them already."""

    def make() -> ChosenPatterns:
        tables, given = fact_tables(own), categories_of(own, config, categories)
        sizes = tables.sizes
        out = ChosenPatterns(given, own.facts, False, sizes.n_rel, sizes.n_facts, sizes.n_ent, given.cats.select("cat").distinct().count())

        # a fact is explained when it is mapped
        spread = staged(_expanded(tables.cells, given).select(F.xxhash64("cs", "r", "co").alias("cand"), "cs", "r", "co", "cell", "t", "n"), "spread")
        patterns = spread.groupBy("cand", "cs", "r", "co").agg(F.sum("n").alias("n_assert"))
        patterns = pattern_model_bits(patterns, own.facts, given, sizes).join(pattern_data_bits(own.facts, given, tables.vectors), "cand")
        patterns, settled = _select(staged(patterns.withColumn("bits", _price(config)), "patterns"), spread.select("cand", "cell", "t", "n"), own.ticks, out.space, config)
        return replace(out, patterns=staged(patterns, "patterns"), settled=settled)

    return once(own.memo, ("patterns", config.categories, config.kinds_known, config.rank_by, config.criterion, config.passes), make)


@dataclass
class ChosenLinks:
    """All candidate links with what was selected, their lags, cover, and whether the passes converged."""

    links: DataFrame
    lags: DataFrame
    cover: DataFrame
    settled: bool


def choose_links(own: Occurrences, config: BuildConfig) -> ChosenLinks:
    """The part of a build that needs no chosen patterns: a fact is explained when something before it leads to it."""
    tables, categories, sizes = tail_tables(own, config.closures), categories_of(own, config), fact_tables(own).sizes
    links, lags = link_candidates(tables.lags, categories, config.max_links, counted=True)
    links, lags = staged(links, "links"), staged(lags, "lags")
    priced = lambda df, among: link_model_bits(df, among).withColumn("bits", _price(config))
    bits = link_data_bits(tails_of(own, config.closures), lags, categories, links, config.assertion_cost, tables.picks)
    links = staged(link_model_bits(links, links).join(bits, "cand").withColumn("bits", _price(config)), "links")
    roles = links.select("cand", "wid", "cx", "cs", "co", "r")
    cover = staged(link_cover(tables.cells, categories, roles), "cover")
    again = lambda df, found: priced(df.select("cand", "rank", "bits_data").join(roles, "cand"), roles.join(found.select("cand"), "cand", "left_semi")).select("cand", "rank", "bits", "bits_data")
    links, settled = _select(links, cover, own.ticks, float(sizes.n_ent) ** 2 * sizes.n_rel, config, again, held_link_bits(links, config))
    return ChosenLinks(staged(links, "links"), lags, cover, settled)


def build(facts: DataFrame, config: BuildConfig | None = None, witness_facts: DataFrame | None = None, prepared: Occurrences | None = None) -> RuleGraph:
    """The rule graph of facts (s, r, o, t); ``prepared`` may come from a build with closures and the same window, horizon and heads."""
    from .workloads import together

    config = config or BuildConfig()
    own = prepared or profiles_and_ticks(facts, config)
    # patterns need no witnesses and links no chosen patterns, so both are found at once; a link brings its tail's pattern along
    base, led = together([lambda: choose_patterns(own, config), lambda: choose_links(own if own.seen is not None else with_witnesses(own, config, witness_facts), config)])
    categories, patterns, space, ticks = base.categories, base.patterns, base.space, own.ticks
    links, lags, cover, linked = led.links, led.lags, led.cover, led.settled

    # what the accepted links explain, tick by tick
    keep = links.where("selected")
    keep = staged(link_model_bits(keep.drop("bits_model"), keep), "chosen")
    explained = cover.join(keep.select("cand"), "cand", "left_semi").select("cell", "t", "n").distinct().groupBy("t").agg(F.sum("n").alias("n_explained"))
    slices = ticks.join(explained, "t", "left").select("t", F.col("n_t").alias("n_facts"), F.coalesce("n_explained", F.lit(0)).alias("n_explained"))
    slices = staged(slices.withColumn("error_bits", error_bits(space, "n_explained", F.col("n_facts") - F.col("n_explained"))), "slices")
    totals = slices.agg(F.sum("error_bits"), F.sum("n_explained"), F.sum("n_facts"), F.max("t"), F.count(F.lit(1))).first()
    costs = lambda df: df.agg(F.coalesce(F.sum("bits_model"), F.lit(0.0)), F.coalesce(F.sum("bits_data"), F.lit(0.0)), F.count(F.lit(1))).first()
    p, q = costs(patterns.where("selected")), costs(keep)
    scalars = {"n_entities": base.n_ent, "n_relations": base.n_rel, "n_categories": base.n_cat, "space": space, "t_end": totals[3], "n_ticks": totals[4], "header_bits": header_bits(base.n_cat, base.n_rel), "model_bits": p[0] + q[0], "assertion_bits": p[1] + q[1], "error_bits": totals[0] or 0.0, "n_patterns": p[2], "n_links": q[2], "n_facts": base.n_facts, "explained_share": (totals[1] or 0) / max(1, totals[2] or 0), "converged": base.settled and linked}
    scalars["total_bits"] = scalars["header_bits"] + scalars["model_bits"] + scalars["assertion_bits"] + scalars["error_bits"]
    # patterns that only links bring in serve time checks, never static evidence
    only = keep.select("cs", "r", "co").distinct().join(patterns.where("selected"), ["cs", "r", "co"], "left_anti")
    kept = patterns.where("selected").unionByName(patterns.join(only, ["cs", "r", "co"], "left_semi"))
    return RuleGraph(categories, staged(kept, "patterns"), keep, staged(lags.join(keep.select("cand"), "cand", "left_semi"), "lags"), slices, scalars, config)


def link_model_bits(links: DataFrame, among: DataFrame) -> DataFrame:
    """Adds bits_model: codes of a link's head (twice for the two legs of a closure) and tail by their frequency
    in the set ``among`` with the link put in, and the direction."""
    total = max(1, among.count())
    heads = among.groupBy("wid", "cx", "cs", "co").agg(F.count(F.lit(1)).alias("n_head"))
    ends = among.groupBy("cs", "r", "co").agg(F.count(F.lit(1)).alias("n_tail"))
    inside = links.join(heads, ["wid", "cx", "cs", "co"], "left").join(ends, ["cs", "r", "co"], "left").join(among.select("cand", F.lit(1).alias("_in")), "cand", "left")
    more = 1 - F.coalesce("_in", F.lit(0))  # a link outside of the set is counted as put in
    role = lambda c: F.log2((F.lit(total) + more) / (F.coalesce(c, F.lit(0)) + more))
    bits = F.log2((F.lit(total) + more).cast("double")) + role("n_head") * F.when(F.col("cx") == NO_CORNER, 1).otherwise(2) + role("n_tail") + 1
    return inside.withColumn("bits_model", bits).drop("n_head", "n_tail", "_in")


def held_link_bits(links: DataFrame, config: BuildConfig) -> Callable[[np.ndarray, np.ndarray], np.ndarray]:
    """The prices of links by :func:`link_model_bits` in the driver, for (candidates, whether chosen): no more rows than the cover that is held there."""
    known: dict[str, np.ndarray] = {}

    def bits(cand: np.ndarray, inside: np.ndarray) -> np.ndarray:
        if not known:
            rows = links.select("cand", F.xxhash64("wid", "cx", "cs", "co"), F.xxhash64("cs", "r", "co"), (F.col("cx") == NO_CORNER).cast("int"), F.col("bits_data").cast("double")).toArrow()
            order = np.argsort(rows.column(0).to_numpy())[np.argsort(np.argsort(cand))]
            known.update(zip(("head", "tail", "chain", "data"), (rows.column(i).to_numpy()[order] for i in range(1, 5)), strict=True))
        total, more = max(1, int(inside.sum())), (~inside).astype(float)

        def role(key: np.ndarray) -> np.ndarray:
            held, count = np.unique(key[inside], return_counts=True)
            at = np.minimum(np.searchsorted(held, key), max(0, len(held) - 1))
            n = np.where(held[at] == key, count[at], 0) if len(held) else np.zeros(len(key))
            return np.log2((total + more) / (n + more))

        model = np.log2(total + more) + role(known["head"]) * np.where(known["chain"] == 1, 1, 2) + role(known["tail"]) + 1
        return {"total": model + known["data"], "data": known["data"], "errors": model}[config.criterion]

    return bits


def corner_cats(categories: cats.Categories) -> DataFrame:
    """(corner, cx): categories of corner profiles, and the stand-in of chains."""
    own = categories.cats.select(F.col("profile").cast("string").alias("corner"), F.col("cat").cast("string").alias("cx"))
    spark = own.sparkSession
    return own.unionByName(spark.range(1).select(F.lit(NO_CORNER).alias("corner"), F.lit(NO_CORNER).alias("cx")))


def _spread_tails(tails: DataFrame, categories: cats.Categories) -> DataFrame:
    return _expanded(tails, categories).join(corner_cats(categories), "corner")


def link_key():
    return F.xxhash64("wid", "cx", "cs", "co", "r").alias("cand")


def lag_counts(tails: DataFrame) -> DataFrame:
    return tails.groupBy("ps", "r", "po", "wid", "corner", "lag").agg(F.count(F.lit(1)).alias("n"))


def link_candidates(tails: DataFrame, categories: cats.Categories, max_links: int | None = None, counted: bool = False) -> tuple[DataFrame, DataFrame]:
    """Links (cand, wid, cx, cs, co, r, n_assert), all or the max_links most asserted, and their lags (cand, lag, cnt); ``counted``: tails come from lag_counts."""
    counts = tails if counted else lag_counts(tails)
    spread = staged(_spread_tails(counts, categories).groupBy("wid", "cx", "cs", "co", "r", "lag").agg(F.sum("n").alias("cnt")), "spread")
    links = spread.groupBy(link_key(), "wid", "cx", "cs", "co", "r").agg(F.sum("cnt").alias("n_assert"))
    lags = spread.select(link_key(), "lag", "cnt")
    if max_links is None:
        return links, lags
    links = cap_links(links, max_links)
    return links, lags.join(links.select("cand"), "cand", "left_semi")


def cap_links(links: DataFrame, max_links: int = 50_000) -> DataFrame:
    """The candidates with most assertions, ties to the larger id: a bound on model size for who asks for one; builds take all candidates."""
    return links.orderBy(F.desc("n_assert"), F.desc("cand")).limit(max_links)


def link_data_bits(tails: DataFrame, lags: DataFrame, categories: cats.Categories, links: DataFrame, cost: str, picks: DataFrame | None = None) -> DataFrame:
    """(cand, bits_data): ``printed`` codes head and tail facts by their frequency among the link's assertions (the two
    legs of a closure as one); ``conditional`` codes which of a tail's earlier witnesses leads to it, and the lag. ``picks`` (ps, r, po, wid, corner, b) where known already."""
    if cost == "printed":
        sides = []
        for side, who in (("head", F.xxhash64("pair", "wid", "corner", "t_seen")), ("tail", F.col("fact_id"))):
            counts = tails.groupBy("ps", "r", "po", "wid", "corner", who.alias("who")).agg(F.count(F.lit(1)).alias("n"))
            counts = _spread_tails(counts, categories).groupBy(link_key(), "who").agg(F.sum("n").alias("n"))
            sides.append(entropy_bits(counts.join(links.select("cand"), "cand", "left_semi"), "cand").withColumnRenamed("bits", side))
        return sides[0].join(sides[1], "cand").select("cand", (F.col("head") + F.col("tail")).alias("bits_data"))
    lag = entropy_bits(lags.select("cand", F.col("cnt").alias("n")), "cand")
    pick = picks
    if pick is None:
        choices = tails.groupBy("fact_id").agg(F.count(F.lit(1)).alias("choices"))
        pick = tails.join(choices, "fact_id").groupBy("ps", "r", "po", "wid", "corner").agg(F.sum(F.log2(F.col("choices").cast("double"))).alias("b"))
    pick = _spread_tails(pick, categories).groupBy(link_key()).agg(F.sum("b").alias("b"))
    return lag.join(pick, "cand").select("cand", (F.col("bits") + F.col("b")).alias("bits_data"))


def link_cover(cells: DataFrame, categories: cats.Categories, links: DataFrame) -> DataFrame:
    """(cand, cell, t, n): cells that a link explains, over categories of both ends and the corner."""
    keys = cells.select("ps", "r", "po", "wid", "corner").distinct()
    spread = _spread_tails(keys, categories).join(links, ["wid", "cx", "cs", "co", "r"]).select("cand", "ps", "r", "po", "wid", "corner").distinct()
    return cells.join(spread, ["ps", "r", "po", "wid", "corner"]).select("cand", "cell", "t", "n").distinct()


def variant(config: BuildConfig, **changes) -> BuildConfig:
    return replace(config, **changes)
