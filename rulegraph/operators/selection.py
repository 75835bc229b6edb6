"""Choosing candidates by description length, in rank order, without a serial loop over data.

Units that candidates explain come in cells: groups of facts of one tick that exactly
the same candidates cover. A candidate is accepted if the error bits it saves, given
what accepted candidates of better rank already explain, exceed its own bits.
"""

from __future__ import annotations

import threading
from collections.abc import Callable
from dataclasses import dataclass

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame, Window
from pyspark.sql import functions as F

from ..functions.mdl import error_bits, log2_choose_array, log2_choose_exact
from ..storage import staged
from .running import running_sums


#: A cover of so many rows (32 bytes each) or fewer is chosen from in the driver, a larger one by the cluster's rounds: one result.
DRIVER_ROWS = 1_000_000

#: The driver holds one cover at a time, however many builds run at once.
_ONE_COVER = threading.Lock()


@dataclass
class HeldCover:
    """A small cover in the driver, rows by candidate and tick: row i is of ``cands[cand[i]]`` and of group ``group[i]``.

    ``unit`` numbers the pairs of cell and tick, groups are pairs of candidate and tick (``g_cand``, ``g_tick``), ``totals`` and
    ``m0`` are the facts of each tick and those explained before.
    """

    cands: np.ndarray
    cand: np.ndarray
    unit: np.ndarray
    n: np.ndarray
    group: np.ndarray
    g_cand: np.ndarray
    g_tick: np.ndarray
    totals: np.ndarray
    m0: np.ndarray

    def gains(self, claim: np.ndarray, above: np.ndarray, space: float) -> np.ndarray:
        """Bits that candidates save by what they claim of each tick when so many facts are explained there already."""
        total = self.totals[self.g_tick]
        saved = log2_choose_array(space - above, total - above) - log2_choose_array(space - above - claim, total - above - claim)
        return _by_group(saved, self.g_cand, len(self.cands))


def _by_group(values: np.ndarray, group: np.ndarray, n: int) -> np.ndarray:
    """Sums over consecutive runs of ``group``, which holds each of 0 to n - 1."""
    return np.add.reduceat(values, np.searchsorted(group, np.arange(n))) if n else np.zeros(0, values.dtype)


def held_cover(cover: DataFrame, ticks: DataFrame, most: int | None = None) -> HeldCover | None:
    """The cover (cand, cell, t, n) and ticks (t, n_t, and m0 where known) in the driver; None where there are more than ``most`` rows."""
    most = DRIVER_ROWS if most is None else most
    if cover.count() > most or ticks.count() > most:
        return None
    rows = cover.select("cand", "cell", "t", F.col("n").cast("long")).toArrow()
    cand, cell, t, n = (rows.column(i).to_numpy() for i in range(4))
    m0 = F.col("m0") if "m0" in ticks.columns else F.lit(0)
    known = ticks.select("t", F.col("n_t").cast("long"), m0.cast("long")).orderBy("t").toArrow()
    at, totals, before = (known.column(i).to_numpy() for i in range(3))
    inside = np.isin(t, at)
    cand, cell, t, n = cand[inside], cell[inside], t[inside], n[inside]
    order = np.lexsort((-n, cell, t, cand))
    cand, cell, t, n = cand[order], cell[order], t[order], n[order]
    same = (cand[1:] == cand[:-1]) & (cell[1:] == cell[:-1]) & (t[1:] == t[:-1])
    keep = np.r_[True, ~same] if len(cand) else np.zeros(0, bool)
    cand, cell, t, n = cand[keep], cell[keep], t[keep], n[keep]
    cands, place = np.unique(cand, return_inverse=True)
    tick = np.searchsorted(at, t)
    by_unit = np.lexsort((t, cell))
    fresh = lambda *keys: np.r_[True, np.logical_or.reduce([k[1:] != k[:-1] for k in keys])] if len(keys[0]) else np.zeros(0, bool)
    unit = np.empty(len(cell), np.int64)
    unit[by_unit] = np.cumsum(fresh(cell[by_unit], t[by_unit])) - 1
    first = fresh(place, tick)
    return HeldCover(cands, place, unit, n, np.cumsum(first) - 1, place[first], tick[first], totals, before)


def pass_held(rank: np.ndarray, bits: np.ndarray, held: HeldCover, space: float) -> tuple[np.ndarray, np.ndarray]:
    """Which candidates of the cover one pass accepts, and their gains: the rounds of :func:`select_fixpoint` over arrays."""
    n_units, n_groups, last = int(held.unit.max(initial=-1)) + 1, len(held.g_cand), np.iinfo(np.int64).max
    by_unit = np.argsort(held.unit, kind="stable")
    starts = np.searchsorted(held.unit[by_unit], np.arange(n_units))
    by_tick = np.lexsort((rank[held.g_cand], held.g_tick))
    tick = held.g_tick[by_tick]
    opened = np.searchsorted(tick, tick)  # where the tick of each group begins
    own = rank[held.cand]
    taken = np.ones(len(held.cands), bool)
    while True:
        best = np.minimum.reduceat(np.where(taken[held.cand], own, last)[by_unit], starts) if n_units else np.zeros(0, np.int64)
        claim = _by_group(np.where(best[held.unit] >= own, held.n, 0), held.group, n_groups)
        claimed = np.where(taken[held.g_cand], claim, 0)[by_tick]
        so_far = np.cumsum(claimed) - claimed
        above = np.empty(n_groups, np.int64)
        above[by_tick] = so_far - so_far[opened]
        gains = held.gains(claim, above + held.m0[held.g_tick], space)
        now = gains > bits
        if (now == taken).all():
            return now, gains
        taken = now


def choose_held(candidates: DataFrame, held: HeldCover, space: float, by: str = "error_reduction", passes: int | None = None, bits_given: Callable[[np.ndarray, np.ndarray], np.ndarray] | None = None) -> tuple[DataFrame, bool]:
    """Candidates (cand, n_assert, bits, ...) with saving, n_cover, rank, gain and selected, and whether the passes converged:
    what :func:`saving_alone`, :func:`rank_candidates` and :func:`select_passes` give. ``bits_given`` (candidates, whether chosen so far)."""
    rows = candidates.select("cand", F.col("n_assert").cast("long"), F.col("bits").cast("double")).toArrow()
    cand, n_assert, bits = (rows.column(i).to_numpy() for i in range(3))
    order = np.argsort(cand)
    cand, n_assert, bits = cand[order], n_assert[order], bits[order]
    if not np.isin(held.cands, cand).all():
        raise ValueError("the cover holds candidates that are not asked about")
    at = np.searchsorted(cand, held.cands)  # candidates of the cover among all
    saving, covered, gain = np.zeros(len(cand)), np.zeros(len(cand), np.int64), np.zeros(len(cand))
    claim = _by_group(held.n, held.group, len(held.g_cand))
    saving[at], covered[at] = held.gains(claim, np.zeros(len(claim), np.int64), space), _by_group(held.n, held.cand, len(held.cands))
    rank = np.empty(len(cand), np.int64)
    rank[np.lexsort((~cand, -n_assert, *([-np.round(saving, 6)] if by == "error_reduction" else [])))] = np.arange(1, len(cand) + 1)
    found, done, converged = np.zeros(len(cand), bool), 0, False
    while not converged and (passes is None or done < passes):
        now = bits if bits_given is None or not done else bits_given(cand, found)
        now, place = np.where(found, -np.inf, now), rank + np.where(found, 0, 1 << 40)
        fresh, gain = 0.0 > now, np.zeros(len(cand))  # what covers nothing gains nothing
        fresh[at], gain[at] = pass_held(place[at], now[at], held, space)
        converged = bool(fresh.sum() in (0, len(cand)) or (done > 0 and fresh.sum() == found.sum()))
        found, done = fresh, done + 1
    made = candidates.sparkSession.createDataFrame(pa.table({"cand": cand, "saving": saving, "n_cover": covered, "rank": rank, "gain": pa.array(gain, mask=~found), "selected": found}))
    return candidates.join(F.broadcast(made), "cand").select(*candidates.columns, "saving", "n_cover", "rank", "gain", "selected"), converged


def choose_small(candidates: DataFrame, cover: DataFrame, ticks: DataFrame, space: float, by: str, passes: int | None, bits_given: Callable[[np.ndarray, np.ndarray], np.ndarray] | None = None) -> tuple[DataFrame, bool] | None:
    """What :func:`choose_held` gives, one cover after the other; None where the cover is not small."""
    with _ONE_COVER:
        held = held_cover(cover, ticks)
        return None if held is None else choose_held(candidates, held, space, by, passes, bits_given)


def saving_alone(cover: DataFrame, ticks: DataFrame, space: float) -> DataFrame:
    """(cand, saving, n_cover): error bits a candidate saves against the empty model."""
    by_tick = cover.groupBy("cand", "t").agg(F.sum("n").alias("c")).join(ticks, "t")
    gain = error_bits(space, F.lit(0), "n_t") - error_bits(space, "c", F.col("n_t") - F.col("c"))
    return by_tick.groupBy("cand").agg(F.sum(gain).alias("saving"), F.sum("c").alias("n_cover"))


def rank_candidates(candidates: DataFrame, by: str = "error_reduction") -> DataFrame:
    """Adds rank from 1: by saving, then assertions, then id, all descending (``assertions``: without saving).

    Savings count to six digits: candidates with one cover are ties, whatever order their bits were summed in.

    Ranks are running counts over range partitions, so no task holds all candidates.
    """
    keys = [F.desc(F.round("saving", 6))] if by == "error_reduction" else []
    ranked = running_sums(candidates.withColumn("_one", F.lit(1)), [*keys, F.desc("n_assert"), F.desc("cand")], {"rank": "_one"})
    return ranked.select(*candidates.columns, F.col("rank").cast("long").alias("rank"))


def claims_of(cover: DataFrame, taken: DataFrame) -> DataFrame:
    """(t, rank, accepted, claim, above): what each candidate would newly explain of a tick, and what accepted ones of
    better rank claim before it. ``cover`` (rank, cell, t, n), ``taken`` (rank, accepted)."""
    marked = cover.join(taken.select("rank", "accepted"), "rank")
    by_cell = Window.partitionBy("cell", "t").orderBy("rank").rowsBetween(Window.unboundedPreceding, -1)
    open_ = marked.withColumn("_held", F.coalesce(F.max(F.col("accepted").cast("int")).over(by_cell), F.lit(0))).where("_held = 0")
    claims = open_.groupBy("t", "rank", "accepted").agg(F.sum("n").alias("claim"))
    above = Window.partitionBy("t").orderBy("rank").rowsBetween(Window.unboundedPreceding, -1)
    return claims.withColumn("above", F.coalesce(F.sum(F.when(F.col("accepted"), F.col("claim"))).over(above), F.lit(0)))


def select_fixpoint(candidates: DataFrame, cover: DataFrame, ticks: DataFrame, space: float, start: DataFrame | None = None) -> DataFrame:
    """Accepted candidates (cand, gain) of one pass in rank order, all candidates at once.

    ``candidates`` (cand, rank, bits), ``cover`` (cand, cell, t, n), ``ticks`` (t, n_t, and m0 where
    something explained that many facts of the tick before). Starts with all accepted, or
    with ``start`` (cand). A round finds each cell's best accepted rank, what every candidate
    would claim given the accepted ones above it, sums claims in rank order by tick, and
    recomputes the gains. The answers of the first i ranks are right after i rounds, so an
    unchanged round is the result of the serial pass, and there is one after as many rounds
    as candidates at the latest (in practice after two or three).
    """
    cover = staged(cover.join(candidates.select("cand", "rank"), "cand").groupBy("rank", "cell", "t").agg(F.max("n").alias("n")), "cover")
    ticks = ticks if "m0" in ticks.columns else ticks.withColumn("m0", F.lit(0))
    bits = candidates.select("cand", "rank", "bits")
    taken = bits.select("cand", "rank", F.lit(True).alias("accepted"))
    if start is not None:
        taken = bits.join(start.select("cand", F.lit(True).alias("_s")), "cand", "left").select("cand", "rank", F.coalesce("_s", F.lit(False)).alias("accepted"))
    mark = lambda df: tuple(df.where("accepted").agg(F.count(F.lit(1)), F.sum("rank"), F.sum(F.xxhash64("rank").bitwiseAND(F.lit((1 << 40) - 1)))).first())
    before = None if start is None else mark(taken)
    while True:
        claims = claims_of(cover, taken).join(ticks, "t").withColumn("m", F.col("above") + F.col("m0"))
        gain = error_bits(space, "m", F.col("n_t") - F.col("m")) - error_bits(space, F.col("m") + F.col("claim"), F.col("n_t") - F.col("m") - F.col("claim"))
        gains = claims.groupBy("rank").agg(F.sum(gain).alias("gain"))
        judged = staged(bits.join(gains, "rank", "left").withColumn("accepted", F.coalesce("gain", F.lit(0.0)) > F.col("bits")), "judged")
        now = mark(judged)
        if now == before:
            return judged.where("accepted").select("cand", F.coalesce("gain", F.lit(0.0)).alias("gain"))
        taken, before = judged.select("cand", "rank", "accepted"), now


def select_passes(ranked: DataFrame, cover: DataFrame, ticks: DataFrame, space: float, passes: int | None = None, bits_given: Callable[[DataFrame, DataFrame], DataFrame] | None = None) -> tuple[DataFrame, bool]:
    """Passes over ranked candidates until one adds nothing (or ``passes`` are over): (accepted, whether it converged).

    What a pass accepted stays and comes first in the next one. ``bits_given`` gives the
    candidates' bits anew for the set chosen so far.
    """
    found, done, n_all, n_found = None, 0, ranked.count(), 0
    while passes is None or done < passes:
        now = ranked
        if found is not None:
            if bits_given is not None:
                now = bits_given(now, found)
            own = now.join(found.select("cand", F.lit(1).alias("_in")), "cand", "left")
            now = own.withColumn("bits", F.when(F.col("_in") == 1, F.lit(float("-inf"))).otherwise(F.col("bits"))).withColumn("rank", F.col("rank") + F.when(F.col("_in") == 1, 0).otherwise(1 << 40)).drop("_in")
        fresh = staged(select_fixpoint(now, cover, ticks, space, found), "accepted")
        n = fresh.count()
        done += 1
        if n in (0, n_all) or (found is not None and n == n_found):
            return fresh, True
        found, n_found = fresh, n
    return found, False


def select_serial(candidates: list[tuple[int, int, float]], cover: dict[int, list[tuple[int, int, int]]], ticks: dict[int, int], space: int) -> list[int]:
    """The same by the plain loop over candidates (cand, rank, bits): the oracle for small inputs."""
    done: set[tuple[int, int]] = set()
    explained = dict.fromkeys(ticks, 0)
    accepted = []
    for cand, _, bits in sorted(candidates, key=lambda x: x[1]):
        new: dict[int, int] = {}
        fresh = [(cell, t, n) for cell, t, n in cover.get(cand, []) if (cell, t) not in done]
        for _, t, n in fresh:
            new[t] = new.get(t, 0) + n
        gain = 0.0
        for t, n in new.items():
            m, total = explained[t], ticks[t]
            gain += log2_choose_exact(space - m, total - m) - log2_choose_exact(space - m - n, total - m - n)
        if gain > bits:
            accepted.append(cand)
            done |= {(cell, t) for cell, t, _ in fresh}
            for t, n in new.items():
                explained[t] += n
    return accepted


def entropy_bits(counts: DataFrame, key: str, n: str = "n", weight: str | None = None) -> DataFrame:
    """(key, bits): n log n - sum of n_i log n_i, the prefix-code length of all occurrences of a key's members; ``weight``: so many members a row."""
    m = F.col(weight) if weight else F.lit(1)
    total = counts.groupBy(key).agg(F.sum(m * F.col(n)).alias("_n"), F.sum(m * F.col(n) * F.log2(F.col(n).cast("double"))).alias("_s"))
    return total.select(key, (F.col("_n") * F.log2(F.col("_n").cast("double")) - F.col("_s")).alias("bits"))


def entropy_of(counts: np.ndarray) -> float:
    n = counts.sum()
    return float(n * np.log2(n) - (counts * np.log2(counts)).sum())
