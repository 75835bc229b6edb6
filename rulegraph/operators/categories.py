"""Entity categories from the relations that entities take part in.

Entities with the same set of relations are interchangeable here, so everything after
the first aggregate works on profiles (distinct relation sets, weighted by how many
entities have them); there are few of these however many entities there are.
"""

from __future__ import annotations

from dataclasses import dataclass

from pyspark.sql import DataFrame, Window
from pyspark.sql import functions as F

from ..storage import staged
from .running import running_sums


def entity_relations(facts: DataFrame, roles: str = "both") -> DataFrame:
    """(eid, r) pairs: as subject, at either end, or at either end with the direction kept in r."""
    subject = facts.select(F.col("s").alias("eid"), "r")
    if roles == "subject":
        return subject.distinct()
    if roles == "directed":
        out = facts.select(F.col("s").alias("eid"), F.concat(F.lit("+"), F.col("r").cast("string")).alias("r"))
        return out.unionByName(facts.select(F.col("o").alias("eid"), F.concat(F.lit("-"), F.col("r").cast("string")).alias("r"))).distinct()
    return facts.select(F.explode(F.array("s", "o")).alias("eid"), "r").distinct()


def entity_profiles(pairs: DataFrame) -> DataFrame:
    """(eid, profile, rels): the sorted relation set of each entity and its hash."""
    sets = pairs.groupBy("eid").agg(F.sort_array(F.collect_set("r")).alias("rels"))
    return sets.select("eid", F.xxhash64("rels").alias("profile"), "rels")


def profiles_of(entities: DataFrame) -> DataFrame:
    return entities.groupBy("profile", "rels").agg(F.count(F.lit(1)).alias("n_ent"))


def frequent_combos(profiles: DataFrame, min_support: int, max_len: int = 3) -> DataFrame:
    """Relation combinations of up to max_len that min_support entities have: (rels, n_ent).

    Level by level: a longer combination is only formed in profiles that hold a
    frequent shorter one with the same beginning.
    """
    long = profiles.select("profile", "n_ent", F.explode("rels").alias("r"))
    single = long.groupBy("r").agg(F.sum("n_ent").alias("c")).where(F.col("c") >= min_support)
    long = long.join(single.select("r"), "r", "left_semi")
    level = long.select("profile", "n_ent", F.array("r").alias("rels"), F.col("r").alias("last"))
    found = single.select(F.array("r").alias("rels"), F.col("c").alias("n_ent"))
    for _ in range(1, max_len):
        grown = level.join(long.select("profile", "r"), "profile").where("r > last")
        grown = grown.select("profile", "n_ent", F.concat("rels", F.array("r")).alias("rels"), F.col("r").alias("last"))
        counted = grown.groupBy("rels").agg(F.sum("n_ent").alias("n_ent")).where(F.col("n_ent") >= min_support)
        level = grown.join(counted.select("rels"), "rels", "left_semi")
        found = found.unionByName(counted)
    return found


def cover(combos: DataFrame, profiles: DataFrame) -> DataFrame:
    """(combo, profile, n_ent) of profiles that hold all relations of a combination."""
    wanted = combos.select("combo", F.size("rels").alias("_size"), F.explode("rels").alias("r"))
    held = profiles.select("profile", "n_ent", F.explode("rels").alias("r"))
    met = wanted.join(held, "r").groupBy("combo", "profile", "_size").agg(F.count(F.lit(1)).alias("_n"), F.first("n_ent").alias("n_ent"))
    return met.where("_n = _size").select("combo", "profile", "n_ent")


def _named(combos: DataFrame) -> DataFrame:
    return combos.withColumn("combo", F.xxhash64("rels"))


def _overlap(both: DataFrame, measure: str) -> DataFrame:
    total = {"jaccard": F.col("a") + F.col("b") - F.col("n"), "min": F.least("a", "b"), "max": F.greatest("a", "b")}[measure]
    return both.withColumn("overlap", F.col("n") / total)


def merge_by_entities(combos: DataFrame, members: DataFrame, overlap: float = 0.9, measure: str = "jaccard") -> DataFrame:
    """Pairs whose entities overlap: union of relations. The cover is recounted exactly by the caller."""
    size = members.groupBy("combo").agg(F.sum("n_ent").alias("n"))
    left = members.select(F.col("combo").alias("x"), "profile", "n_ent")
    both = left.join(members.select(F.col("combo").alias("y"), "profile"), "profile").where("x < y").groupBy("x", "y").agg(F.sum("n_ent").alias("n"))
    both = both.join(size.select(F.col("combo").alias("x"), F.col("n").alias("a")), "x").join(size.select(F.col("combo").alias("y"), F.col("n").alias("b")), "y")
    close = _overlap(both, measure).where(F.col("overlap") > overlap)
    rels = combos.select("combo", "rels")
    close = close.join(rels.select(F.col("combo").alias("x"), F.col("rels").alias("rx")), "x").join(rels.select(F.col("combo").alias("y"), F.col("rels").alias("ry")), "y")
    return _named(close.select(F.array_sort(F.array_union("rx", "ry")).alias("rels")).distinct())


def merge_by_relations(combos: DataFrame, members: DataFrame, overlap: float = 0.9, measure: str = "jaccard") -> tuple[DataFrame, DataFrame]:
    """Pairs whose relations overlap: common relations with the entities of either. New combos and their members."""
    long = combos.select("combo", F.size("rels").alias("k"), F.explode("rels").alias("r"))
    both = long.select(F.col("combo").alias("x"), F.col("k").alias("a"), "r").join(long.select(F.col("combo").alias("y"), F.col("k").alias("b"), "r"), "r").where("x < y")
    both = both.groupBy("x", "y", "a", "b").agg(F.count(F.lit(1)).alias("n"), F.sort_array(F.collect_list("r")).alias("rels"))
    close = _named(_overlap(both, measure).where(F.col("overlap") > overlap))
    pairs = close.select("combo", F.explode(F.array("x", "y")).alias("_from"))
    joined = pairs.join(members.withColumnRenamed("combo", "_from"), "_from").select("combo", "profile", "n_ent").distinct()
    return close.select("combo", "rels").distinct(), joined


@dataclass(frozen=True)
class CategoryConfig:
    k: int = 3
    max_len: int = 3
    min_support: int | None = None
    overlap: float = 0.9
    relation_overlap: float = 0.9
    measure: str = "jaccard"
    roles: str = "both"
    aggregate: bool = True


def _collapsed(combos: DataFrame, members: DataFrame) -> tuple[DataFrame, DataFrame]:
    """Combinations with equal covers become the largest of their relation sets (they overlap fully, so merging forms that union)."""
    same = members.groupBy("combo").agg(F.hash(F.sort_array(F.collect_list("profile"))).alias("_h"), F.xxhash64(F.sort_array(F.collect_list("profile"))).alias("_c"), F.sum("n_ent").alias("n_ent"))
    held = combos.select("combo", "rels").join(same, "combo")
    joined = held.groupBy("_c", "_h", "n_ent").agg(F.array_sort(F.array_distinct(F.flatten(F.collect_list("rels")))).alias("rels"), F.min("combo").alias("_one"))
    named = staged(_named(joined.select("rels", "_one")).groupBy("combo", "rels").agg(F.min("_one").alias("_one")), "combos")
    moved = members.withColumnRenamed("combo", "_one").join(named.select("combo", "_one"), "_one").select("combo", "profile", "n_ent")
    return named.select("combo", "rels"), staged(moved.distinct(), "members")


def needed(combos: DataFrame, members: DataFrame, k: int) -> DataFrame:
    """Combinations (combo) that :func:`prune` can still keep: some member has fewer than k larger ones.

    More combinations only push others back, and all that a merge by entities makes of a
    combination lies behind it for the same members, so what is not needed now is never
    needed, nor is anything merged from it.
    """
    size = members.groupBy("combo").agg(F.sum("n_ent").alias("n")).join(combos.select("combo", F.size("rels").alias("_k")), "combo")
    order = Window.partitionBy("profile").orderBy(F.desc("n"), F.desc("_k"), "combo")
    placed = members.select("combo", "profile").join(size, "combo").withColumn("_place", F.row_number().over(order))
    return placed.groupBy("combo").agg(F.min("_place").alias("_place")).where(F.col("_place") <= k).select("combo")


def close_combos(combos: DataFrame, members: DataFrame, profiles: DataFrame, config: CategoryConfig) -> tuple[DataFrame, DataFrame]:
    """Merges combinations, told apart by their members, in turn by entities and by relations until nothing new appears.

    Combinations that no entity can need for its k categories are left out before and
    after each round (see :func:`needed`), which keeps the closure as small as its use:
    at most k combinations a profile are merged with each other.
    """
    keep = lambda c, m: (c.join(w := staged(needed(c, m, config.k), "needed"), "combo", "left_semi"), m.join(w, "combo", "left_semi"))
    combos, members = keep(combos, members)
    while True:
        finer = merge_by_entities(combos, members, config.overlap, config.measure).join(combos.select("combo"), "combo", "left_anti")
        coarse, coarse_members = merge_by_relations(combos, members, config.relation_overlap, config.measure)
        coarse = coarse.join(combos.select("combo"), "combo", "left_anti")
        fresh = finer.select("combo", "rels").unionByName(coarse.select("combo", "rels")).dropDuplicates(["combo"])
        fresh_members = cover(finer, profiles).unionByName(coarse_members.join(coarse.select("combo"), "combo", "left_semi")).distinct()
        fresh = staged(fresh, "fresh")
        if fresh.isEmpty():
            return combos, members
        old = combos
        combos, members = _collapsed(combos.unionByName(fresh), members.unionByName(fresh_members))
        combos, members = keep(combos, members)
        combos, members = staged(combos, "combos"), staged(members, "members")
        if combos.join(old.select("combo"), "combo", "left_anti").isEmpty():
            return combos, members


def prune(combos: DataFrame, members: DataFrame, k: int) -> DataFrame:
    """Combinations kept by taking them in order of cover until each entity has k: (combo, rels, n_ent, rank).

    A combination is kept iff some member has fewer than k kept ones before it. Starting
    from all kept, recounting until nothing changes reaches the sequential answer: the
    first i ranks are right after i rounds at the latest.
    """
    size = members.groupBy("combo").agg(F.sum("n_ent").alias("n_ent"))
    ranked = combos.select("combo", "rels").join(size, "combo").withColumn("_one", F.lit(1))
    ranked = staged(running_sums(ranked, [F.desc("n_ent"), F.desc(F.size("rels")), "combo"], {"rank": "_one"}).drop("_one"), "ranked")
    held = members.select("combo", "profile").join(ranked.select("combo", "rank"), "combo")
    kept, before = ranked.select("combo"), -1
    while True:
        flagged = held.join(kept.withColumn("_k", F.lit(1)), "combo", "left")
        ahead = Window.partitionBy("profile").orderBy("rank").rowsBetween(Window.unboundedPreceding, -1)
        need = flagged.withColumn("_before", F.coalesce(F.sum("_k").over(ahead), F.lit(0))).where(F.col("_before") < k).select("combo").distinct()
        need = staged(need, "kept")
        now = need.agg(F.count(F.lit(1)), F.sum(F.hash("combo").cast("long"))).first()
        if now == before:
            return ranked.join(need, "combo", "left_semi")
        kept, before = need, now


@dataclass
class Categories:
    """entity -> profile -> categories. ``entities`` (eid, profile), ``cats`` (profile, cat), ``combos`` (cat, rels, n_ent).

    ``named``: the profile is the first letter of the name, and nobody is asked about who is not among the entities, so
    profiles are read off names without a join.
    """

    entities: DataFrame
    cats: DataFrame
    combos: DataFrame | None = None
    named: bool = False

    def of_entities(self) -> DataFrame:
        return self.entities.join(self.cats, "profile").select("eid", "cat")


@dataclass
class Combos:
    """Frequent combinations (combo, rels) with their members (combo, profile, n_ent), before any number of categories matters."""

    profiles: DataFrame
    combos: DataFrame
    members: DataFrame


def frequent(entities: DataFrame, config: CategoryConfig) -> Combos:
    """What :func:`learn` begins with: the same for all ``k``."""
    profiles = staged(profiles_of(entities), "profiles")
    total = profiles.agg(F.sum("n_ent")).first()[0] or 0
    support = config.min_support or max(2, total // 1000)
    combos = staged(_named(frequent_combos(profiles, support, config.max_len)), "combos")
    if config.aggregate:
        return Combos(profiles, *_collapsed(combos, cover(combos, profiles)))
    return Combos(profiles, combos, staged(cover(combos, profiles), "members"))


def learn(facts: DataFrame, config: CategoryConfig | None = None, entities: DataFrame | None = None, begun: Combos | None = None) -> Categories:
    """Categories of all entities of facts; ``entities`` are their profiles and ``begun`` their frequent combinations where known already."""
    config = config or CategoryConfig()
    entities = staged(entity_profiles(entity_relations(facts, config.roles)), "entities") if entities is None else entities
    begun = begun or frequent(entities, config)
    combos, members = close_combos(begun.combos, begun.members, begun.profiles, config) if config.aggregate else (begun.combos, begun.members)
    kept = prune(combos, members, config.k)
    cats = members.join(kept.select("combo"), "combo", "left_semi").select("profile", F.col("combo").alias("cat")).distinct()
    return Categories(entities.select("eid", "profile"), staged(cats, "cats"), staged(kept.select(F.col("combo").alias("cat"), "rels", "n_ent"), "kept"))


def by_kind(facts: DataFrame, named: bool = False) -> Categories:
    """The kind that an entity's name begins with as its only category (where kinds are known).

    ``named``: only entities of these facts will be asked about.
    """
    entities = facts.select(F.col("s").alias("eid")).unionByName(facts.select(F.col("o").alias("eid"))).distinct()
    entities = entities.select("eid", F.substring("eid", 1, 1).alias("profile"))
    kinds = entities
    if named:  # no need to tell entities apart first
        kinds = facts.select(F.explode(F.array(F.substring("s", 1, 1), F.substring("o", 1, 1))).alias("profile"))
    kinds = kinds.select("profile", F.col("profile").alias("cat")).distinct()
    return Categories(entities, staged(kinds, "kinds") if named else kinds, named=named)


def describe(categories: Categories, top: int = 4) -> DataFrame:
    """For people: the relations that define a category and some of its entities (the least names: each task passes on ``top`` of a category)."""
    place = F.row_number().over(Window.partitionBy("cat").orderBy("eid"))
    least = categories.of_entities().withColumn("_i", place).where(F.col("_i") <= top).groupBy("cat").agg(F.sort_array(F.collect_list("eid")).cast("array<string>").alias("entities"))
    sizes = categories.entities.groupBy("profile").agg(F.count(F.lit(1)).alias("n")).join(categories.cats, "profile").groupBy("cat").agg(F.sum("n").alias("n_entities"))
    out = least.join(sizes, "cat").select("cat", "entities", "n_entities")
    if categories.combos is not None:
        out = out.join(categories.combos.select("cat", F.array_join(F.transform("rels", lambda r: r.cast("string")), ", ").alias("relations")), "cat", "left")
    return out
