"""What came before a fact: chains in the same pair and triangles over a third entity.

A *witness* is something that happened between s and o: a fact of the pair (chain), or
two facts that join s and o over a corner entity (closure). Both are rows
(s, o, wid, corner, t), with wid a hash of kind, relations and directions, so all that
follows treats them alike. The corner column holds the corner's profile; chains have
the profile of no entity there.
"""

from __future__ import annotations

from pyspark.sql import DataFrame, Window
from pyspark.sql import functions as F

from ..storage import staged

NO_CORNER = "-"


def pair_sequences(facts: DataFrame) -> DataFrame:
    """Facts with their place in the time-ordered sequence of their pair."""
    order = Window.partitionBy("s", "o").orderBy("t", "r")
    return facts.withColumn("place", F.row_number().over(order))


def chain_pairs(facts: DataFrame, horizon: int, mode: str = "within", max_prev: int | None = None) -> DataFrame:
    """(head, tail) facts of one pair in order of time, at most horizon ticks apart.

    ``adjacent`` takes neighbours in the sequence only; ``within`` all pairs, optionally
    with at most max_prev facts in between. Buckets of horizon ticks make the range join
    an equality join in which every pair meets once.
    """
    seq = pair_sequences(facts)
    if mode == "adjacent":
        w = Window.partitionBy("s", "o").orderBy("t", "r")
        out = seq.select("s", "o", F.lag("r").over(w).alias("r_head"), F.lag("t").over(w).alias("t_head"), F.col("r").alias("r_tail"), F.col("t").alias("t_tail"))
        return out.where(F.col("t_head").isNotNull() & (F.col("t_tail") - F.col("t_head") <= horizon)).withColumn("lag", F.col("t_tail") - F.col("t_head"))
    width = max(1, horizon)
    head = seq.select("s", "o", F.col("r").alias("r_head"), F.col("t").alias("t_head"), F.col("place").alias("p_head"), F.floor(F.col("t") / width).alias("b"))
    tail = seq.select("s", "o", F.col("r").alias("r_tail"), F.col("t").alias("t_tail"), F.col("place").alias("p_tail"), F.explode(F.array(F.floor(F.col("t") / width), F.floor(F.col("t") / width) - 1)).alias("b"))
    both = head.join(tail, ["s", "o", "b"]).where((F.col("p_head") < F.col("p_tail")) & (F.col("t_tail") - F.col("t_head") <= horizon))
    if max_prev:
        both = both.where(F.col("p_tail") - F.col("p_head") <= max_prev)
    return both.select("s", "o", "r_head", "t_head", "r_tail", "t_tail", (F.col("t_tail") - F.col("t_head")).alias("lag"))


def half_edges(facts: DataFrame) -> DataFrame:
    """Each fact seen from both ends: leaf, corner, relation, 1 if the corner is the subject, time."""
    out = facts.select(F.col("o").alias("leaf"), F.col("s").alias("corner"), "r", F.lit(1).alias("d"), "t")
    return out.unionByName(facts.select(F.col("s").alias("leaf"), F.col("o").alias("corner"), "r", F.lit(0).alias("d"), "t"))


def chain_witnesses(facts: DataFrame) -> DataFrame:
    return facts.select("s", "o", F.xxhash64(F.lit("chain"), "r").alias("wid"), F.lit(NO_CORNER).alias("corner"), "t")


def _block(t: str, width: int | None):
    """The block of ticks that t lies in; one block where there is no horizon."""
    return F.lit(0).cast("long") if width is None else F.floor(F.col(t) / width).cast("long")


def closure_witnesses(facts: DataFrame, entities: DataFrame, asked: DataFrame, window: int, horizon: int | None = None, kinds: DataFrame | None = None) -> DataFrame:
    """Two facts over a corner, at most window ticks apart, for asked pairs; their time is the later one.

    ``kinds`` (wid, r1, d1, r2, d2) are those wanted, a small table; by default all. Facts that are no leg of any do not meet.

    With a horizon ``asked`` has s, o and t, and only legs that a fact of that tick can still
    see are met, block of ticks by block of ticks. In each block a pair is opened from its end with
    fewer facts, so the sum over pairs stays below (number of facts) ** 1.5 and a hub is
    opened only where both ends are hubs.
    """
    width = None if horizon is None else max(1, horizon + window)
    half = half_edges(facts).where("leaf <> corner")
    if kinds is not None:
        legs = kinds.select(F.col("r1").alias("r"), F.col("d1").alias("d")).unionByName(kinds.select(F.col("r2").alias("r"), F.col("d2").alias("d"))).distinct()
        half = half.join(F.broadcast(legs), ["r", "d"], "left_semi")
    half = half.distinct().withColumn("b", _block("t", width))
    if width is not None:  # a fact sees legs of its own block and of the one before
        half = half.withColumn("b", F.explode(F.array(F.col("b"), F.col("b") + 1)))
    pairs = (asked.withColumn("b", _block("t", width)) if width is not None else asked.withColumn("b", F.lit(0).cast("long"))).select("s", "o", "b").distinct()
    degree = half.groupBy("leaf", "b").agg(F.count(F.lit(1)).alias("n"))
    end = lambda c: degree.select(F.col("leaf").alias(c), "b", F.col("n").alias(f"n_{c}"))
    pairs = pairs.join(end("s"), ["s", "b"]).join(end("o"), ["o", "b"])
    turned = F.col("n_o") < F.col("n_s")
    pairs = pairs.select(F.when(turned, F.col("o")).otherwise(F.col("s")).alias("near"), F.when(turned, F.col("s")).otherwise(F.col("o")).alias("far"), "b", turned.alias("turned"))
    leg = lambda who, i: half.select(F.col("leaf").alias(who), F.col("corner").alias("x"), "b", F.col("r").alias(f"r{i}"), F.col("d").alias(f"d{i}"), F.col("t").alias(f"t{i}"))
    met = pairs.join(leg("near", 1), ["near", "b"]).where("x <> far").join(leg("far", 2), ["far", "x", "b"]).where(F.abs(F.col("t1") - F.col("t2")) <= window)
    met = met.join(entities.select(F.col("eid").alias("x"), F.col("profile").cast("string").alias("corner")), "x")
    side = lambda c, d: F.when(F.col("turned"), F.col(c)).otherwise(F.col(d))
    wid = F.xxhash64(F.lit("closure"), side("r2", "r1"), side("d2", "d1"), side("r1", "r2"), side("d1", "d2"))
    found = met.select(side("far", "near").alias("s"), side("near", "far").alias("o"), wid.alias("wid"), "corner", F.greatest("t1", "t2").alias("t"))
    return (found if kinds is None else found.join(F.broadcast(kinds.select("wid")), "wid", "left_semi").select(*found.columns)).distinct()


#: So many pairs of profiles or fewer are sent to every task; beyond, first legs are not told apart by them: one result.
PROFILE_PAIRS = 10_000


def earlier_closures(facts: DataFrame, window: int, horizon: int, since: int | None = None) -> DataFrame:
    """Facts (fact_id, pair, ps, r, po, t) with wid, corner and t_seen of the closures before them, some more than once: the
    closures of all_witnesses over :func:`closure_witnesses`, without a join from witnesses back to facts.

    ``facts`` (fact_id, s, ps, r, o, po, t) are a set, and what comes before them too. A leg stands in one block of ticks, a pair
    is asked in its own block and the one before and carries its facts along, so legs that none of them can see go before the
    second leg is met. A pair is opened from its end with fewer legs in the two blocks. A first leg goes too where no fact joins
    profiles like those of its corner and of the far end, as long as few profiles meet (``PROFILE_PAIRS``). With ``since`` only
    facts from that tick on ask.
    """
    width = max(1, horizon + window)
    out = facts.select(F.col("o").alias("leaf"), F.col("s").alias("corner"), F.col("ps").alias("px"), "r", F.lit(1).alias("d"), "t")
    legs = out.unionByName(facts.select(F.col("s").alias("leaf"), F.col("o").alias("corner"), F.col("po").alias("px"), "r", F.lit(0).alias("d"), "t"))
    legs = legs.where("leaf <> corner").withColumn("b", _block("t", width))
    asked = (facts if since is None else facts.where(F.col("t") >= since)).groupBy("s", "o", "ps", "po", _block("t", width).alias("b")).agg(F.collect_list(F.struct("fact_id", "r", "t")).alias("asked"), (F.min("t") - width).alias("low"), F.max("t").alias("high"))
    degree = legs.groupBy("leaf", "b").agg(F.count(F.lit(1)).alias("n")).select("leaf", F.explode(F.array(F.col("b"), F.col("b") + 1)).alias("b"), "n").groupBy("leaf", "b").agg(F.sum("n").alias("n"))
    end = lambda c: degree.select(F.col("leaf").alias(c), "b", F.col("n").alias(f"n_{c}"))
    pairs = asked.join(end("s"), ["s", "b"]).join(end("o"), ["o", "b"]).withColumn("turned", F.col("n_o") < F.col("n_s"))
    swap = lambda a, b: F.when(F.col("turned"), F.col(a)).otherwise(F.col(b))
    pairs = pairs.select(swap("o", "s").alias("near"), swap("s", "o").alias("far"), F.explode(F.array(F.col("b"), F.col("b") - 1)).alias("b"), "turned", "ps", "po", "asked", "low", "high")
    leg = lambda who, i: legs.select(F.col("leaf").alias(who), F.col("corner").alias("x"), "b", F.col("px").alias(f"px{i}"), F.col("r").alias(f"r{i}"), F.col("d").alias(f"d{i}"), F.col("t").alias(f"t{i}"))
    seen = lambda t: (F.col(t) >= F.col("low")) & (F.col(t) < F.col("high"))
    first = pairs.join(leg("near", 1), ["near", "b"]).where((F.col("x") != F.col("far")) & seen("t1"))
    pair_of = lambda a, b: facts.select(F.col(a).alias("pfar"), F.col(b).alias("px1"))
    meeting = staged(pair_of("ps", "po").unionByName(pair_of("po", "ps")).distinct(), "meeting")
    if meeting.count() <= PROFILE_PAIRS:
        first = first.withColumn("pfar", swap("ps", "po")).join(F.broadcast(meeting), ["pfar", "px1"], "left_semi").drop("pfar")
    # the second leg stands in all blocks that a first leg near to it may be in
    near_blocks = F.sequence(F.floor((F.col("t2") - window) / width).cast("long"), F.floor((F.col("t2") + window) / width).cast("long"))
    met = first.join(leg("far", 2).drop("px2").withColumn("b", F.explode(near_blocks)), ["far", "x", "b"]).where(seen("t2") & (F.abs(F.col("t1") - F.col("t2")) <= window))
    wid = F.xxhash64(F.lit("closure"), swap("r2", "r1"), swap("d2", "d1"), swap("r1", "r2"), swap("d1", "d2"))
    pair = F.when(F.col("turned"), F.xxhash64("far", "near")).otherwise(F.xxhash64("near", "far"))
    found = met.select(pair.alias("pair"), "ps", "po", wid.alias("wid"), F.col("px1").cast("string").alias("corner"), F.greatest("t1", "t2").alias("t_seen"), F.explode("asked").alias("a"))
    found = found.where((F.col("t_seen") < F.col("a.t")) & (F.col("a.t") - F.col("t_seen") <= horizon))
    return found.select("a.fact_id", "pair", "ps", "a.r", "po", "a.t", "wid", "corner", "t_seen")


def closure_kinds(rels: DataFrame) -> DataFrame:
    """(wid, r1, d1, r2, d2): every pair of legs over relations (r); relations squared rows, a closed set."""
    side = lambda i: rels.select(F.col("r").alias(f"r{i}"), F.explode(F.array(F.lit(0), F.lit(1))).alias(f"d{i}"), F.lit(1).alias("_j"))
    return side(1).join(side(2), "_j").select(F.xxhash64(F.lit("closure"), "r1", "d1", "r2", "d2").alias("wid"), "r1", "d1", "r2", "d2")


def linked_closures(links: DataFrame, facts: DataFrame) -> DataFrame | None:
    """The kinds of closures among facts that links start from, for :func:`closure_witnesses`; None if there are none."""
    own = links.where(F.col("cx") != NO_CORNER).select("wid").distinct()
    kinds = staged(closure_kinds(facts.select("r").distinct()).join(own, "wid", "left_semi"), "kinds")
    return None if kinds.isEmpty() else kinds


def witness_names(facts: DataFrame) -> DataFrame:
    """(wid, kind, label) for reading links: over the relations that occur (closed set, small)."""
    rels = facts.select("r").distinct()
    chain = rels.select(F.xxhash64(F.lit("chain"), "r").alias("wid"), F.lit("chain").alias("kind"), F.col("r").cast("string").alias("label"))
    arrow = lambda i: F.concat(F.col(f"r{i}").cast("string"), F.when(F.col(f"d{i}") == 1, F.lit("(from corner)")).otherwise(F.lit("(to corner)")))
    closure = closure_kinds(rels).select("wid", F.lit("closure").alias("kind"), F.concat(arrow(1), F.lit(" & "), arrow(2)).alias("label"))
    return chain.unionByName(closure)


def latest_witnesses(facts: DataFrame, witnesses: DataFrame, horizon: int | None = None, strict: bool = True) -> DataFrame:
    """For each fact (fact_id, s, o, t) the latest earlier time of each kind of witness of its pair.

    With a horizon: an equality join on blocks of ticks and a maximum. Facts and witnesses are
    sets and ticks are whole, so a pair has at most horizon x kinds rows a block on either side,
    however hot it is. Without one, an as-of join without a range predicate: questions and answers
    are put into one sequence for each (pair, kind) and the last answer is carried forward.
    Facts of the same tick do not see each other where strict.
    """
    key = ["s", "o", "wid", "corner"]
    if horizon is not None:
        met = all_witnesses(facts, witnesses, horizon, strict)
        return met.groupBy("fact_id", "wid", "corner").agg(F.min("lag").alias("lag"), F.max("t_seen").alias("t_seen"))
    own = witnesses.select(*key, "t").distinct()
    ask = facts.select("fact_id", "s", "o", F.col("t").alias("at")).join(own.select(*key).distinct(), ["s", "o"])
    ask = ask.select(*key, "at", F.lit(None).cast("long").alias("t"), "fact_id", F.lit(0 if strict else 1).alias("kind"))
    known = own.select(*key, F.col("t").alias("at"), "t", F.lit(None).cast("long").alias("fact_id"), F.lit(1 if strict else 0).alias("kind"))
    order = Window.partitionBy(*key).orderBy("at", "kind").rowsBetween(Window.unboundedPreceding, Window.currentRow)
    found = ask.unionByName(known).withColumn("seen", F.last("t", True).over(order)).where(F.col("fact_id").isNotNull() & F.col("seen").isNotNull())
    return found.select("fact_id", "wid", "corner", (F.col("at") - F.col("seen")).alias("lag"), F.col("seen").alias("t_seen"))


def earlier_chains(facts: DataFrame, horizon: int | None, past: DataFrame | None = None, latest: bool = False, relations: list[str] | None = None) -> DataFrame:
    """Facts (s, r, o, t and what else they hold) with wid, corner, lag and t_seen of every earlier fact of their pair (or
    the latest of each relation): the chains of all_witnesses and latest_witnesses by one shuffle and no join.

    ``past`` are the facts that may come before, as a set or not; by default the facts themselves. With a horizon a row
    holds what its pair has in so many ticks, at most horizon x relations. Without one the latest times of the given
    ``relations`` are carried along.
    """
    out = with_earlier(facts, horizon, past, latest, relations).select(*facts.columns, F.explode("_seen").alias("_x"))
    return out.select(*facts.columns, F.xxhash64(F.lit("chain"), "_x.r").alias("wid"), F.lit(NO_CORNER).alias("corner"), (F.col("t") - F.col("_x.t")).alias("lag"), F.col("_x.t").alias("t_seen"))


def with_earlier(facts: DataFrame, horizon: int | None, past: DataFrame | None = None, latest: bool = False, relations: list[str] | None = None) -> DataFrame:
    """Facts with ``_seen``, all (r, t) of :func:`earlier_chains` in one list: facts kept by pair are not shuffled."""
    own = facts if past is None else facts.withColumn("_ask", F.lit(True)).unionByName(past.select("s", "r", "o", "t"), True)
    w = Window.partitionBy("s", "o").orderBy("t")
    known = F.lit(True) if past is None else F.col("_ask").isNull()
    if horizon is None:
        w = w.rangeBetween(Window.unboundedPreceding, -1)
        held = F.array(*[F.struct(F.lit(r).alias("r"), F.max(F.when(known & (F.col("r") == r), F.col("t"))).over(w).alias("t")) for r in relations])
        seen = own.withColumn("_seen", F.filter(held, lambda x: x["t"].isNotNull()))
    else:
        seen = own.withColumn("_seen", F.collect_set(F.when(known, F.struct("r", "t"))).over(w.rangeBetween(-horizon, -1)))
        if latest:
            seen = seen.withColumn("_seen", F.filter("_seen", lambda x: ~F.exists("_seen", lambda y: (y["r"] == x["r"]) & (y["t"] > x["t"]))))
    seen = seen if past is None else seen.where("_ask")
    return seen.select(*facts.columns, "_seen")


def all_witnesses(facts: DataFrame, witnesses: DataFrame, horizon: int | None = None, strict: bool = True) -> DataFrame:
    """For each fact every earlier witness of its pair, horizon ticks back: the same columns as the latest ones.

    An equality join on blocks of ticks; without a horizon all earlier witnesses of the pair meet.
    """
    width = None if horizon is None else max(1, horizon)
    own = witnesses.select("s", "o", "wid", "corner", F.col("t").alias("t_seen")).distinct().withColumn("b", _block("t_seen", width))
    if width is not None:
        own = own.withColumn("b", F.explode(F.array(F.col("b"), F.col("b") + 1)))
    ask = facts.select("fact_id", "s", "o", F.col("t").alias("at"), _block("t", width).alias("b"))
    met = ask.join(own, ["s", "o", "b"]).where("t_seen < at" if strict else "t_seen <= at")
    out = met.select("fact_id", "wid", "corner", (F.col("at") - F.col("t_seen")).alias("lag"), "t_seen")
    return out.where(F.col("lag") <= horizon) if horizon is not None else out
