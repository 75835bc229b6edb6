"""Sharding by balanced label propagation.

Documents with equal texts are linked. Every linked document starts in a shard drawn
from its id; in each round the members of a group look at their neighbours' shards and
move to the most frequent one that has room, as far as the shard's quota allows.
Members of a group in the same shard are interchangeable, so a round works on rows
(group, shard, count): at most one for each group and shard. Then moves are matched: all
groups leave at once and are seated again whole, large ones first, in the shard they wish
for while it has room, else where most room is, so what leaves a shard makes room in it.
Unlinked documents have no neighbours and fill what is left, which makes the counts exact.
A group is cut only if no shard has room for it: fewer than ``shards`` groups of one size.

A group with over ``giant`` of a shard's quota cannot sit in one shard for sure; there
are at most shards / giant of these, placed first, over as few shards as hold them.
"""

from __future__ import annotations

import numpy as np
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from .common import dealt_rank, shuffle_partitions, staged


def _unit(*columns) -> F.Column:
    """A number in [0, 1) from a hash."""
    return (F.xxhash64(*columns).bitwiseAND(F.lit((1 << 53) - 1)).cast("double")) / float(1 << 53)


def _drawn(unit, weights: list[float]):
    """The shard whose share of the cumulated weights holds ``unit``."""
    total = sum(weights) or 1.0
    edges = np.cumsum(weights) / total
    out = F.lit(len(weights) - 1)
    for s in range(len(weights) - 2, -1, -1):
        out = F.when(unit < float(edges[s]), s).otherwise(out)
    return out.cast("int")


def quotas(rows: int, shards: int) -> list[int]:
    return [rows // shards + (s < rows % shards) for s in range(shards)]


def propagate(state: DataFrame, room: list[int]) -> DataFrame:
    """Moves groups (g, shard, n) towards their most frequent shard with room left in ``room``.

    A round costs one aggregate of the state; loads and wishes, one number for each
    shard, are all that the driver sees. Where more wish to enter a shard than it has
    room for, a hash draws who may; the rest look again in the next round, from a table
    written in between. It ends when nobody wishes to move, or a round brings nobody nearer.
    """
    shards, turn, before = len(room), 0, None
    while True:
        load = {r["shard"]: r["n"] for r in state.groupBy("shard").agg(F.sum("n").alias("n")).collect()}
        left = [max(0, room[s] - load.get(s, 0)) for s in range(shards)]
        # over its quota a shard attracts nobody; among others more neighbours win, then more room
        pull = F.element_at(F.array([F.lit(float(1 + left[s]) if load.get(s, 0) <= room[s] else 0.0) for s in range(shards)]), F.col("shard") + 1)
        seen = state.withColumn("_pull", F.when(pull > 0, F.struct(F.col("n").alias("n"), pull.alias("pull"), F.xxhash64("g", "shard", F.lit(turn)).alias("h"), F.col("shard").alias("shard"))))
        groups = seen.groupBy("g").agg(F.max("_pull.shard").alias("_any"), F.max("_pull").alias("_best"), F.sum("n").alias("_size"), F.count(F.lit(1)).alias("_parts"))
        wish = groups.select("g", "_size", "_parts", F.coalesce(F.col("_best.shard"), _drawn(_unit("g", F.lit(turn)), [float(x) for x in left])).alias("_to"), F.coalesce(F.col("_best.n"), F.lit(0)).alias("_there"))
        wish = wish.withColumn("_in", F.col("_size") - F.col("_there"))
        asked = {r["_to"]: r["n"] for r in wish.where(F.col("_in") > 0).groupBy("_to").agg(F.sum("_in").alias("n")).collect()}
        if not asked or (before is not None and sum(asked.values()) >= before):
            return state
        before, turn = sum(asked.values()), turn + 1
        share = F.element_at(F.array([F.lit(min(1.0, 0.95 * left[s] / asked[s]) if asked.get(s) else 1.0) for s in range(shards)]), F.col("_to") + 1)
        chosen = wish.withColumn("_go", (F.col("_in") == 0) | (_unit("g", F.lit(1000 + turn)) < share))
        moved = chosen.where("_go").select("g", F.col("_to").alias("shard"), F.col("_size").alias("n"))
        kept = state.join(chosen.where(~F.col("_go")).select("g"), "g", "left_semi")
        state = staged(moved.unionByName(kept.select("g", "shard", "n")), "labels")


def seats(sizes: dict[tuple[int, int], int], room: list[int]) -> dict[tuple[int, int], list[tuple[int, int]]]:
    """How many groups of each (wish, size) go to which shards: lists of (shard, count), the rest has no room.

    ``sizes`` counts groups by wish and size; distinct sizes are few, as their sum is bounded by the rows.
    """
    left, plan = list(room), {}
    for n in sorted({n for _, n in sizes}, reverse=True):
        over = {}
        for s in range(len(room)):
            asked = sizes.get((s, n), 0)
            stay = min(asked, max(0, left[s]) // n)
            left[s] -= stay * n
            plan[s, n] = [(s, stay)] if stay else []
            over[s] = asked - stay
        for s, k in over.items():
            for to in sorted(range(len(room)), key=lambda t: (-left[t], t)):
                go = min(k, max(0, left[to]) // n)
                if go:
                    plan[s, n].append((to, go))
                    left[to] -= go * n
                    k -= go
    return plan


def seated(state: DataFrame, room: list[int], buckets: int) -> DataFrame:
    """(g, shard): one shard for each group of state (g, shard, n), null if none has room for the whole group."""
    groups = state.groupBy("g").agg(F.max(F.struct("n", "shard")).alias("m"), F.sum("n").alias("size")).select("g", F.col("m.shard").alias("wish"), "size")
    ranked = staged(dealt_rank(groups, ["wish", "size"], ["g"], "rank", buckets), "seats")
    sizes = {(r["wish"], r["size"]): r["n"] for r in ranked.groupBy("wish", "size").agg(F.count(F.lit(1)).alias("n")).collect()}
    ranges = []
    for (wish, size), parts in seats(sizes, room).items():
        low = 0
        for s, k in parts:
            ranges.append((wish, size, low, low + k, s))
            low += k
    spans = state.sparkSession.createDataFrame(ranges, "_w int, _s long, _low long, _high long, shard int")
    on = (F.col("wish") == F.col("_w")) & (F.col("size") == F.col("_s")) & (F.col("rank") >= F.col("_low")) & (F.col("rank") < F.col("_high"))
    return ranked.join(F.broadcast(spans), on, "left").select("g", "shard")


def cut_links(found: DataFrame) -> DataFrame:
    """One row for the result of :func:`shard_rows`: groups of equal texts, groups in several shards, links (members beyond a
    group's first) and links cut (members outside of their group's largest shard)."""
    parts = found.where("linked").groupBy("text_id", "shard").agg(F.count(F.lit(1)).alias("n"))
    groups = parts.groupBy("text_id").agg(F.sum("n").alias("size"), F.max("n").alias("best"), F.count(F.lit(1)).alias("shards"))
    return groups.agg(F.count(F.lit(1)).alias("n_groups"), F.coalesce(F.sum((F.col("shards") > 1).cast("long")), F.lit(0)).alias("n_cut_groups"), F.coalesce(F.sum(F.col("size") - 1), F.lit(0)).alias("n_links"), F.coalesce(F.sum(F.col("size") - F.col("best")), F.lit(0)).alias("n_cut_links"))


def shard_rows(docs: DataFrame, shards: int = 8, giant: float = 0.125) -> DataFrame:
    """Puts documents (doc_id, text) into shards with counts at most one apart.

    Returns doc_id, size (UTF-8 bytes plus 1), text_crc32, shard, slot (gapless from 0 in
    each shard), linked, text_id (digest of the text). A null text has no bytes and is linked with empty texts; repeated
    rows count each; an empty table gives no rows.
    """
    spark = docs.sparkSession
    text = F.coalesce(F.col("text"), F.lit(""))
    rows = docs.select(F.col("doc_id").cast("long").alias("doc_id"), (F.octet_length(text) + 1).cast("long").alias("size"), F.crc32(F.encode(text, "UTF-8")).alias("text_crc32"), F.unhex(F.sha2(text, 256)).alias("g"))
    rows = staged(rows, "rows")
    total = rows.count()
    quota = quotas(total, shards)
    groups = staged(rows.groupBy("g").agg(F.count(F.lit(1)).alias("n")).where("n > 1"), "groups")
    large = {bytes(r["g"]): r["n"] for r in groups.where(F.col("n") > max(1, int(min(quota) * giant))).collect()} if total else {}
    held = [0] * shards
    plan: dict[bytes, list[tuple[int, int]]] = {}
    for g, n in sorted(large.items(), key=lambda x: (-x[1], x[0])):
        while n:
            fit = [s for s in range(shards) if quota[s] - held[s] >= n]
            s = min(fit, key=lambda s: (quota[s] - held[s], s)) if fit else max(range(shards), key=lambda s: (quota[s] - held[s], -s))
            take = min(n, quota[s] - held[s])
            plan.setdefault(g, []).append((s, take))
            held[s] += take
            n -= take
    room = [q - h for q, h in zip(quota, held, strict=True)]
    ids = [F.lit(bytearray(g)) for g in plan]
    is_large = F.col("g").isin(*ids) if ids else F.lit(False)
    start = _drawn(_unit("doc_id", "g"), [float(x) for x in room])
    small = groups.where(~is_large).select("g")
    linked = rows.join(small, "g", "left_semi")
    state = propagate(staged(linked.groupBy("g", start.alias("shard")).agg(F.count(F.lit(1)).alias("n")), "labels"), room) if total else None
    if state is None:
        return rows.select("doc_id", "size", "text_crc32", F.lit(0).alias("shard"), F.lit(0).cast("long").alias("slot"), F.lit(False).alias("linked"), F.col("g").alias("text_id"))
    buckets = shuffle_partitions(spark)
    settled = seated(state, room, buckets).select("g", F.col("shard").alias("_to"), F.lit(True).alias("_small"))
    wanted = rows.join(settled, "g", "left")
    # the wish of a member of a giant group: a share of its hash range for each of the group's shards
    giant_wish = F.lit(None).cast("int")
    for g, parts in plan.items():
        own = _drawn(_unit("doc_id", "size", F.lit(7)), [float(sum(n for s, n in parts if s == k)) for k in range(shards)])
        giant_wish = F.when(F.col("g") == F.lit(bytearray(g)), own).otherwise(giant_wish)
    # members of a group that no shard has room for fill up like unlinked rows
    wish = F.coalesce(giant_wish, F.col("_to"), F.lit(-1))
    wanted = wanted.select("doc_id", "size", "text_crc32", "g", wish.alias("wish"), giant_wish.isNotNull().alias("_giant"), (giant_wish.isNotNull() | F.col("_small").isNotNull()).alias("linked"))
    # the draw for a giant group's rows is not exact: whole groups rank before them
    ranked = staged(dealt_rank(wanted, ["wish", "_giant"], ["doc_id", "g"], "rank", buckets), "wishes")
    found = ranked.groupBy("wish").agg(F.count(F.lit(1)).alias("n"), F.sum((~F.col("_giant")).cast("long")).alias("whole")).collect()
    counts, ahead = ({r["wish"]: r[c] for r in found} for c in ("n", "whole"))
    shift = F.element_at(F.array([F.lit(int(ahead.get(s, 0))) for s in range(-1, shards)]), F.col("wish") + 2)
    ranked = ranked.withColumn("rank", F.col("rank") + F.when(F.col("_giant"), shift).otherwise(0)).drop("_giant")
    limit = F.element_at(F.array([F.lit(0), *[F.lit(q) for q in quota]]), F.col("wish") + 2)
    stays = ranked.where(F.col("rank") < limit).select("doc_id", "size", "text_crc32", F.col("wish").alias("shard"), F.col("rank").alias("slot"), "linked", F.col("g").alias("text_id"))
    pool = ranked.where(F.col("rank") >= limit)
    pool = dealt_rank(pool.withColumn("_all", F.lit(0)), ["_all"], ["doc_id", "g"], "place", buckets)
    given = [min(quota[s], counts.get(s, 0)) for s in range(shards)]
    edges = np.cumsum([0] + [q - n for q, n in zip(quota, given, strict=True)])
    shard, slot = F.lit(None).cast("int"), F.lit(None).cast("long")
    for s in range(shards - 1, -1, -1):
        inside = F.col("place") < int(edges[s + 1])
        shard = F.when(inside, s).otherwise(shard)
        slot = F.when(inside, F.col("place") - int(edges[s]) + given[s]).otherwise(slot)
    filled = pool.select("doc_id", "size", "text_crc32", shard.alias("shard"), slot.alias("slot"), "linked", F.col("g").alias("text_id"))
    return stays.unionByName(filled)
