"""Queries that run whole methods and experiments over the fixtures."""

from __future__ import annotations

from dataclasses import replace

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from ..baselines import embeddings
from ..baselines.simple import METHODS
from ..functions.mdl import code_bits
from ..operators import categories as cats
from ..operators import evaluation as ev
from ..operators import occurrences as oc
from ..operators import scoring as sc
from ..operators.updating import OnlineConfig, explained_ticks
from ..sources import facts as fx
from ..storage import staged
from ..streaming import online
from . import duration as du
from . import workloads as wl
from .build import BuildConfig, RuleGraph, build, link_candidates, link_data_bits, map_patterns, pattern_data_bits, pattern_model_bits, profiled
from .build import link_model_bits as priced_links
from .build import pattern_counts as counted
from .oracles import FACTS, KINDS, PATTERNS, choose, draw, over
from .queries import query, r6

_HELD: dict[tuple, object] = {}


def held(spark: SparkSession, sf_dir: str, name: str, what: str, make):
    """Experiments and graphs are made once for each session and input; their tables are in the shared folder."""
    key = (spark.sparkContext.applicationId, sf_dir, name, what)
    if key not in _HELD:
        _HELD[key] = make()
    return _HELD[key]


def exp(spark, d, name) -> wl.Experiment:
    return held(spark, d, name, "experiment", lambda: wl.of_fixture(spark, d, name))


def offline(spark, d, name) -> DataFrame:
    """The offline facts of an experiment where nothing else of it is asked for: no errors are made, no table is written.

    Facts are not made a set here: that costs a shuffle of all of them, and what asks does not count them.
    """
    facts = fx.ROWS[name](spark, d)
    end = held(spark, d, name, "end", lambda: ev.offline_end(facts))
    return facts.where(F.col("t") <= F.lit(end))


def graph(spark, d, name) -> RuleGraph:
    """Built from the offline facts alone: who asks for the graph only makes no errors and keeps no tables of them."""
    return held(spark, d, name, "graph", lambda: build(offline(spark, d, name).distinct(), wl.build_config(name)))


def run(spark, d, name) -> wl.Run:
    """The whole method over the test part, with the updater: made once, other experiments rest on the history it kept."""
    return held(spark, d, name, "run", lambda: wl.detect(exp(spark, d, name), graph(spark, d, name), wl.score_config(name)))


# ---- parts of the method that SQL can follow ---------------------------------------------------------------


def all_patterns(facts: DataFrame, by: cats.Categories) -> RuleGraph:
    """A graph of all candidate patterns and no links: static evidence without selection."""
    p = counted(facts, by).select(F.xxhash64("cs", "r", "co").alias("cand"), "cs", "r", "co", "n_assert", F.lit(True).alias("selected"))
    # small, and read in many places: not counted anew from all facts in each
    return RuleGraph(by, staged(p, "patterns"), None, None, None, {}, BuildConfig())


@query(over("trade", PATTERNS, select="SELECT s, f.r, o, CAST(t AS BIGINT) AS t, round(1.0 / n, 12) AS score_static FROM facts f JOIN pats p ON substr(s, 1, 1) = cs AND f.r = p.r AND substr(o, 1, 1) = co"))
def static_score_kinds(spark, d):
    facts = staged(fx.trade(spark, d), "facts")
    return sc.static_score(facts, all_patterns(facts, cats.by_kind(facts, True))).select("s", "r", "o", "t", F.round("score_static", 12).alias("score_static"))


_BITS = f"""sizes AS (SELECT substr(e, 1, 1) AS cat, count(*) AS n FROM ents GROUP BY 1), tot AS (SELECT (SELECT count(*) FROM ents) AS e, (SELECT count(*) FROM facts) AS f, (SELECT count(*) FROM sizes) AS c),
rel AS (SELECT r, count(*) AS n FROM facts GROUP BY r)"""


@query(over("trade", KINDS, PATTERNS, _BITS, select="SELECT cs, p.r, co, round(log2(c) - log2(a.n / e) - log2(b.n / e) - log2(rel.n / f) + 1, 6) AS bits_model FROM pats p JOIN sizes a ON cs = a.cat JOIN sizes b ON co = b.cat JOIN rel ON p.r = rel.r, tot"))
def pattern_bits(spark, d):
    facts = fx.trade(spark, d)
    by = cats.by_kind(facts)
    return pattern_model_bits(counted(facts, by), facts, by).select("cs", "r", "co", r6("bits_model").alias("bits_model"))


@query(over("trade", PATTERNS, "sb AS (SELECT substr(s, 1, 1) AS cs, r, substr(o, 1, 1) AS co, sum(k * log2(k)) AS x FROM (SELECT s, r, substr(o, 1, 1) AS o, count(*) AS k FROM facts GROUP BY ALL) GROUP BY ALL)", "ob AS (SELECT substr(s, 1, 1) AS cs, r, substr(o, 1, 1) AS co, sum(k * log2(k)) AS x FROM (SELECT substr(s, 1, 1) AS s, r, o, count(*) AS k FROM facts GROUP BY ALL) GROUP BY ALL)", select="SELECT p.cs, p.r, p.co, round(2 * n * log2(n) - sb.x - ob.x, 3) AS bits_data FROM pats p JOIN sb ON p.cs = sb.cs AND p.r = sb.r AND p.co = sb.co JOIN ob ON p.cs = ob.cs AND p.r = ob.r AND p.co = ob.co"))
def pattern_assertion_bits(spark, d):
    facts = fx.trade(spark, d)
    by = cats.by_kind(facts)
    keyed = counted(facts, by).withColumn("cand", F.xxhash64("cs", "r", "co")).join(pattern_data_bits(facts, by), "cand")
    return keyed.select("cs", "r", "co", F.round("bits_data", 3).alias("bits_data"))


def all_links(facts: DataFrame, horizon: int, bits: bool = False, space: bool = False) -> RuleGraph:
    """All patterns and all chain links of a horizon, kinds as categories: the model before any selection.

    ``facts`` are a set that is read several times (staged); ``bits``: with the links' bits_data; ``space``: with the number
    of cells a tick has.
    """
    by = cats.by_kind(facts, True)
    own = profiled(facts.select("s", "r", "o", "t"), by)
    keyed = own.select("s", "o", F.xxhash64("s", "r", "o", "t").alias("fact_id"), F.xxhash64("s", "o").alias("pair"), "ps", "r", "po", "t")
    tails = oc.earlier_chains(keyed, horizon).drop("s", "o")
    tails = staged(tails, "tails") if bits else tails
    links, lags = link_candidates(tails, by)
    if bits:
        links = links.join(link_data_bits(tails, lags, by, links, "printed"), "cand")
    model = replace(all_patterns(facts, by), links=staged(links, "links"), lags=staged(lags, "lags"), config=BuildConfig(kinds_known=True, closures=False, horizon=horizon))
    if not space:
        return model
    ends = facts.select(F.col("s").alias("e")).unionByName(facts.select(F.col("o").alias("e"))).agg(F.countDistinct("e")).first()[0]
    rels = facts.agg(F.countDistinct("r")).first()[0]
    return replace(model, scalars={"space": float(ends) ** 2 * rels})


_ALL = """pairs_ AS (SELECT f.s, f.o, f.r, f.t, h.r AS r_head, h.t AS t_head FROM facts f JOIN facts h ON f.s = h.s AND f.o = h.o AND h.t < f.t AND f.t - h.t <= 30),
lk AS (SELECT substr(s, 1, 1) AS cs, substr(o, 1, 1) AS co, r_head, r, count(*) AS n FROM pairs_ GROUP BY ALL)"""
_HEADS = "chain_heads AS (SELECT substr(s, 1, 1) AS cs, substr(o, 1, 1) AS co, r_head, r, sum(k * log2(k)) AS x FROM (SELECT s, o, r_head, r, t_head, count(*) AS k FROM pairs_ GROUP BY ALL) GROUP BY ALL)"
_TAILS = "chain_tails AS (SELECT substr(s, 1, 1) AS cs, substr(o, 1, 1) AS co, r_head, r, sum(k * log2(k)) AS y FROM (SELECT s, o, r_head, r, t, count(*) AS k FROM pairs_ GROUP BY ALL) GROUP BY ALL)"


def _relation_heads(facts: DataFrame) -> DataFrame:
    return facts.select("r").distinct().select(F.xxhash64(F.lit("chain"), "r").alias("wid"), F.col("r").alias("r_head"))


@query(over("lifecycle", _ALL, _HEADS, _TAILS, select="SELECT cs, co, r_head, r, n AS n_assert, round(2 * n * log2(n) - x - y, 2) AS bits FROM lk JOIN chain_heads USING (cs, co, r_head, r) JOIN chain_tails USING (cs, co, r_head, r)"))
def link_bits(spark, d):
    """Chain links of a month with the code length of head and tail facts among their assertions."""
    facts = staged(fx.lifecycle(spark, d), "facts")
    links = all_links(facts, 30, bits=True).links.join(_relation_heads(facts), "wid")
    return links.select("cs", "co", "r_head", "r", "n_assert", F.round("bits_data", 2).alias("bits"))


@query(over("lifecycle", _ALL, "e AS (SELECT count(*) AS m FROM lk)", "hd AS (SELECT cs, co, r_head, count(*) AS a FROM lk GROUP BY ALL)", "tl AS (SELECT cs, co, r, count(*) AS b FROM lk GROUP BY ALL)", select="SELECT lk.cs, lk.co, lk.r_head, lk.r, round(log2(m) - log2(a / m) - log2(b / m) + 1, 6) AS bits_model FROM lk, e, hd, tl WHERE lk.cs = hd.cs AND lk.co = hd.co AND lk.r_head = hd.r_head AND lk.cs = tl.cs AND lk.co = tl.co AND lk.r = tl.r"))
def link_model_bits(spark, d):
    """Codes of links by the frequency of their heads and tails in the set."""
    facts = staged(fx.lifecycle(spark, d), "facts")
    links = all_links(facts, 30).links
    return priced_links(links, links).join(_relation_heads(facts), "wid").select("cs", "co", "r_head", "r", r6("bits_model").alias("bits_model"))


@query(over("lifecycle", _ALL, "h AS (SELECT substr(s, 1, 1) AS cs, substr(o, 1, 1) AS co, r_head, r, t - t_head AS lag, count(*) AS c FROM pairs_ GROUP BY ALL)", PATTERNS, "asked AS (SELECT s, o, r, t, r_head, t - max(t_head) AS lag FROM pairs_ GROUP BY s, o, r, t, r_head)", "fit AS (SELECT a.s, a.o, a.r, a.t, a.r_head, sum(CASE WHEN abs(h.lag - a.lag) <= 2 THEN c ELSE 0 END) / sum(c) AS share FROM asked a JOIN h ON substr(a.s, 1, 1) = h.cs AND substr(a.o, 1, 1) = h.co AND a.r_head = h.r_head AND a.r = h.r GROUP BY a.s, a.o, a.r, a.t, a.r_head)", "sums AS (SELECT f.s, f.r, f.o, f.t, sum(share * p.n) AS e FROM fit f JOIN pats p ON substr(f.s, 1, 1) = p.cs AND f.r = p.r AND substr(f.o, 1, 1) = p.co GROUP BY f.s, f.r, f.o, f.t)", select="SELECT f.s, f.r, f.o, CAST(f.t AS BIGINT) AS t, round(coalesce(e, 0.0), 3) AS ev_temporal FROM facts f LEFT JOIN sums ON f.s = sums.s AND f.r = sums.r AND f.o = sums.o AND f.t = sums.t"))
def temporal_evidence_kinds(spark, d):
    """Temporal evidence of all facts over all chain links, no recursion, kinds as categories."""
    facts = fx.with_ids(staged(fx.lifecycle(spark, d), "facts"))
    config = sc.ScoreConfig(K=0, L=2, horizon=30, closures=False, out_edge_penalty=False)
    found = sc.score(facts, None, all_links(facts, 30), config)
    return found.select("s", "r", "o", "t", F.round("ev_temporal", 3).alias("ev_temporal"))


_LED = "led AS (SELECT DISTINCT s, o, r, t FROM pairs_)"
_SPACE = "z AS (SELECT (SELECT count(*) FROM ents) * (SELECT count(*) FROM ents) * (SELECT count(DISTINCT r) FROM facts) AS space)"


@query(over("lifecycle", KINDS, _ALL, _LED, _SPACE, "g AS (SELECT f.t, count(*) AS n_facts, count(led.t) AS n_explained FROM facts f LEFT JOIN led ON f.s = led.s AND f.o = led.o AND f.r = led.r AND f.t = led.t GROUP BY f.t)", select=f"SELECT CAST(t AS BIGINT) AS t, n_facts, n_explained, round({choose('space - n_explained', 'n_facts - n_explained')}, 3) AS error_bits FROM g, z"))
def online_error_bits(spark, d):
    """The monitor's bits of every tick, over all chain links, kinds as categories."""
    facts = staged(fx.lifecycle(spark, d), "facts")
    return explained_ticks(facts, None, all_links(facts, 30, space=True), 30).select("t", "n_facts", "n_explained", F.round("error_bits", 3).alias("error_bits"))


@query(over("lifecycle", _ALL, _LED, select="SELECT round((SELECT count(*) FROM led) / (SELECT count(*) FROM facts), 6) AS explained_share"))
def explained_share(spark, d):
    facts = staged(fx.lifecycle(spark, d), "facts")
    ticks = explained_ticks(facts, None, all_links(facts, 30, space=True), 30)
    return ticks.agg(r6(F.sum("n_explained") / F.sum("n_facts")).alias("explained_share"))


@query(over("lifecycle", _ALL, "hh AS (SELECT cs, co, r_head, r, lag, count(*) AS c FROM (SELECT substr(s, 1, 1) AS cs, substr(o, 1, 1) AS co, r_head, r, t - t_head AS lag FROM pairs_) GROUP BY ALL)", "us AS (SELECT cs, co, r_head, r, max(lag) AS longest, arg_max(lag, c * 1000 - lag) AS usual FROM hh GROUP BY ALL)", "last_ AS (SELECT max(t) AS e FROM facts)", "asked AS (SELECT f.s, f.o, f.r AS r_head, f.t, u.r, u.usual, u.longest, EXISTS (SELECT 1 FROM pairs_ p WHERE p.s = f.s AND p.o = f.o AND p.r_head = f.r AND p.t_head = f.t AND p.r = u.r AND p.t - f.t <= u.longest) AS came FROM facts f JOIN us u ON substr(f.s, 1, 1) = u.cs AND substr(f.o, 1, 1) = u.co AND f.r = u.r_head, last_ WHERE f.t + u.longest <= e)", "strong AS (SELECT substr(s, 1, 1) AS cs, substr(o, 1, 1) AS co, r_head, r FROM asked GROUP BY ALL HAVING count(*) FILTER (came) >= 0.5 * count(*))", "due AS (SELECT a.s, a.r, a.o, a.t + a.usual AS t, count(*) AS asked_by FROM asked a JOIN strong k ON substr(a.s, 1, 1) = k.cs AND substr(a.o, 1, 1) = k.co AND a.r_head = k.r_head AND a.r = k.r WHERE NOT came GROUP BY ALL)", select="SELECT s, r, o, CAST(t AS BIGINT) AS t, asked_by FROM due d WHERE NOT EXISTS (SELECT 1 FROM facts f WHERE f.s = d.s AND f.r = d.r AND f.o = d.o AND f.t = d.t)"))
def missing_successors(spark, d):
    """What strong chain links lead to and the data lacks, over the whole table, kinds as categories: the planted gaps among them."""
    facts = fx.with_ids(fx.lifecycle_by_pair(spark, d))
    due = sc.missing_successors(facts, None, all_links(facts, 30), sc.ScoreConfig(horizon=30, closures=False))
    due = staged(due.groupBy("s", "r", "o", "t").agg(F.countDistinct("asker", "r").alias("asked_by")), "due")
    # only facts of pairs that lack something can be what is due
    known = facts.select("s", "r", "o", "t").join(due.select("s", "o").distinct(), ["s", "o"], "left_semi")
    return due.join(known, ["s", "r", "o", "t"], "left_anti")


# ---- data sets and errors -----------------------------------------------------------------------------------


def _stat(name: str) -> str:
    return f"SELECT '{name}' AS fixture, (SELECT count(*) FROM (SELECT s FROM facts UNION SELECT o FROM facts)) AS entities, count(DISTINCT r) AS relations, count(DISTINCT t) AS ticks, count(*) AS facts FROM facts"


@query(" UNION ALL ".join(f"(WITH {FACTS[n]} {_stat(n)})" for n in fx.FIXTURES))
def w1_dataset_stats(spark, d):
    parts = []
    for name, make in fx.FIXTURES.items():
        f = make(spark, d)
        ends = f.select(F.col("s").alias("e")).unionByName(f.select(F.col("o").alias("e"))).agg(F.countDistinct("e").alias("entities"))
        rest = f.agg(F.countDistinct("r").alias("relations"), F.countDistinct("t").alias("ticks"), F.count(F.lit(1)).alias("facts"))
        parts.append(ends.join(rest).select(F.lit(name).alias("fixture"), "entities", "relations", "ticks", "facts"))
    out = parts[0]
    for p in parts[1:]:
        out = out.unionByName(p)
    return out


_SPLIT = "tk AS (SELECT t, row_number() OVER (ORDER BY t) AS i, count(*) OVER () AS n FROM (SELECT DISTINCT t FROM facts)), sp AS (SELECT t, CASE WHEN i <= CAST(floor(n * 0.6) AS BIGINT) THEN 'offline' WHEN i <= CAST(floor(n * 0.7) AS BIGINT) THEN 'validation' ELSE 'test' END AS part FROM tk)"


@query(over("lifecycle", _SPLIT, select="SELECT part, count(*) AS n, CAST(min(facts.t) AS BIGINT) AS first_t, CAST(max(facts.t) AS BIGINT) AS last_t FROM facts JOIN sp ON facts.t = sp.t GROUP BY part"))
def w2_split(spark, d):
    cut = ev.time_split(fx.lifecycle(spark, d), (0.6, 0.1, 0.3))
    return cut.groupBy("part").agg(F.count(F.lit(1)).alias("n"), F.min("t").alias("first_t"), F.max("t").alias("last_t"))


_RATE = int(0.15 * 16**8)


@query(over("trade", f"b AS (SELECT {draw('bucket', 'e')} % 256 AS b, min(e) AS e FROM (SELECT DISTINCT o AS e FROM facts) GROUP BY 1)", "rl AS (SELECT r, row_number() OVER (ORDER BY r) - 1 AS j, count(*) OVER () AS n FROM (SELECT DISTINCT r FROM facts))", f"ch AS (SELECT *, {draw('conceptual2', 's', 'r', 'o', 't')} AS d FROM facts WHERE {draw('conceptual', 's', 'r', 'o', 't')} < {_RATE})", "made AS (SELECT s, r, e AS o, t FROM ch JOIN b ON (d // 2) % 256 = b.b WHERE d % 2 = 0 AND e <> s UNION SELECT s, rl.r, o, t FROM ch JOIN rl ON (d // 2) % rl.n = rl.j WHERE d % 2 = 1)", select="SELECT s, r, o, CAST(t AS BIGINT) AS t FROM made m WHERE NOT EXISTS (SELECT 1 FROM facts f WHERE f.s = m.s AND f.r = m.r AND f.o = m.o)"))
def w2_conceptual(spark, d):
    facts = fx.trade(spark, d)
    return ev.inject_conceptual(facts, facts)


@query(over("clicks", "z AS (SELECT min(t) AS low, max(t) - min(t) + 1 AS span FROM facts)", f"ch AS (SELECT *, {draw('time2', 's', 'r', 'o', 't')} AS d FROM facts WHERE {draw('time', 's', 'r', 'o', 't')} < {_RATE})", "made AS (SELECT DISTINCT s, r, o, low + (t - low + span // 4 + d % (span - 2 * (span // 4))) % span AS t FROM ch, z)", select="SELECT s, r, o, CAST(t AS BIGINT) AS t FROM made EXCEPT SELECT s, r, o, t FROM facts"))
def w2_time(spark, d):
    facts = fx.clicks(spark, d)
    return ev.inject_time(facts, facts)


@query(over("lifecycle", select=f"SELECT s, r, o, CAST(t AS BIGINT) AS t FROM facts WHERE {draw('missing', 's', 'r', 'o', 't')} < {_RATE}"))
def w2_missing(spark, d):
    return ev.inject_missing(fx.lifecycle(spark, d))[1]


# ---- experiments ----------------------------------------------------------------------------------------------


@query()
def w3_accuracy(spark, d):
    """The rule graph on lifecycle: three kinds of errors in a stream that rests on verdicts only."""
    return wl.rows_of(spark, wl.measured("lifecycle", "rule graph", run(spark, d, "lifecycle").measures()))


@query()
def w3_accuracy_trade(spark, d):
    return wl.rows_of(spark, wl.measured("trade", "rule graph", run(spark, d, "trade").measures()))


def _baselines(spark, d, name: str, methods: dict) -> DataFrame:
    e = exp(spark, d, name)
    found = wl.together([lambda m=m, f=f: wl.measured(name, m, wl.plain(e, f).measures()) for m, f in methods.items()])
    return wl.rows_of(spark, [row for rows in found for row in rows])


@query()
def w3_baselines(spark, d):
    """Four plain baselines on lifecycle, three kinds of errors."""
    return _baselines(spark, d, "lifecycle", METHODS)


@query()
def w3_baselines_trade(spark, d):
    return _baselines(spark, d, "trade", METHODS)


@query()
def w3_embeddings(spark, d):
    """All embedding families on the click graph, three kinds of errors."""
    return _baselines(spark, d, "clicks", embeddings.scorers())


@query()
def w3_embeddings_lifecycle(spark, d):
    return _baselines(spark, d, "lifecycle", embeddings.scorers())


@query()
def w3_score_forms(spark, d):
    """Forms of the time score over one history: as printed, by disagreeing lags, by agreeing lags, and against expectation."""
    e, own = exp(spark, d, "lifecycle"), run(spark, d, "lifecycle")
    forms = {"literal": ("literal", "evidence"), "mismatch": ("mismatch", "evidence"), "agreement": ("agreement", "evidence"), "expectation": ("agreement", "expectation")}
    config = lambda gap: wl.score_config("lifecycle", gap=gap)
    found = wl.together([lambda n=n, g=g, f=f: wl.measured("lifecycle", n, wl.against_kept(e, own, own.graph, config(g), f).measures(("time",))) for n, (g, f) in forms.items()])
    return wl.rows_of(spark, [row for rows in found for row in rows])


@query()
def w3_negative_control(spark, d):
    """Clicks have no temporal order, so temporal scores must not beat chance there."""
    return wl.rows_of(spark, wl.measured("clicks", "rule graph", run(spark, d, "clicks").measures(("time",))))


@query()
def w4_training_share(spark, d):
    return spark.createDataFrame(wl.proportion_sweep(exp(spark, d, "lifecycle"), run(spark, d, "lifecycle")), wl.SWEEP)


@query()
def w5_ablation(spark, d):
    """Variants of the scores and of updating, three kinds of errors."""
    return wl.rows_of(spark, wl.ablation(exp(spark, d, "lifecycle"), run(spark, d, "lifecycle"), ("full", "no updater", "no recursion", "unit weights in scores")))


@query()
def w5_ablation_graph(spark, d):
    """Variants of the build, three kinds of errors."""
    return wl.rows_of(spark, wl.ablation(exp(spark, d, "lifecycle"), run(spark, d, "lifecycle"), ("full", "no category aggregation", "no closure links", "ranking by assertions only")))


@query()
def w6_over_time(spark, d):
    """Time-error accuracy by 60-day bins, with the updater and frozen, over all facts and over triples never seen offline."""
    e, own = exp(spark, d, "lifecycle"), run(spark, d, "lifecycle")
    frozen = held(spark, d, "lifecycle", "frozen", lambda: wl.detect(e, graph(spark, d, "lifecycle"), wl.score_config("lifecycle"), updater=False))
    parts = [wl.over_time(e, r, "time", 60, unseen).select("*", F.lit(u).alias("updater"), F.lit(unseen).alias("unseen_only")) for u, r in ((True, own), (False, frozen)) for unseen in (False, True)]
    out = parts[0]
    for p in parts[1:]:
        out = out.unionByName(p)
    return out


@query()
def w7_depth(spark, d):
    return spark.createDataFrame(wl.depth_sweep(exp(spark, d, "lifecycle"), run(spark, d, "lifecycle")), wl.SWEEP)


@query()
def w8_window(spark, d):
    return spark.createDataFrame(wl.window_sweep(exp(spark, d, "lifecycle"), run(spark, d, "lifecycle")), wl.SWEEP)


@query()
def w8_grid(spark, d):
    """Depth and window chosen by the F-score on validation."""
    return spark.createDataFrame(wl.grid_search(exp(spark, d, "lifecycle"), run(spark, d, "lifecycle")), wl.GRID)


@query()
def w9_categories(spark, d):
    return spark.createDataFrame(wl.category_sweep(exp(spark, d, "lifecycle"), run(spark, d, "lifecycle")), wl.SWEEP)


@query()
def w10_build_report(spark, d):
    return spark.createDataFrame(wl.build_report(fx.lifecycle(spark, d), "lifecycle"), wl.REPORT)


@query()
def w11_category_readout(spark, d):
    """Categories need neither errors nor candidates: the offline facts' relation sets give them, as in the build."""
    return cats.describe(held(spark, d, "lifecycle", "categories", lambda: cats.learn(offline(spark, d, "lifecycle"), wl.build_config("lifecycle").categories)))


@query()
def w12_link_readout(spark, d):
    g = graph(spark, d, "lifecycle")
    return g.links.join(oc.witness_names(offline(spark, d, "lifecycle")), "wid").select("kind", F.col("label").alias("precursor"), F.col("cs").cast("string").alias("subject_category"), "r", F.col("co").cast("string").alias("object_category"), "n_assert", r6("saving").alias("saving"))


_DURATION = {"horizon": 400, "closures": False}


def _case(spark, d) -> du.DurationCase:
    return held(spark, d, "validity", "case", lambda: du.duration_case(fx.validity(spark, d)))


def _sides(spark, d) -> dict[str, RuleGraph]:
    return held(spark, d, "validity", "graphs", lambda: du.duration_graphs(_case(spark, d).offline, replace(wl.build_config("trade"), **_DURATION)))


def _duration_scores() -> sc.ScoreConfig:
    return wl.score_config("trade", horizon=400, L=30, K=1, closures=False)


@query()
def w13_duration(spark, d):
    """Three kinds of errors among duration facts, by the mean of four graphs."""
    return wl.rows_of(spark, du.duration_experiment(_case(spark, d), replace(wl.build_config("trade"), **_DURATION), _duration_scores(), _sides(spark, d)))


def _flattened(spark, d, hows: tuple[str, ...]) -> DataFrame:
    case, config = _case(spark, d), replace(wl.build_config("trade"), **_DURATION)
    found = wl.together([lambda h=h: du.flattening_experiment(case, h, config, _duration_scores()) for h in hows])
    return wl.rows_of(spark, [row for rows in found for row in rows])


@query()
def w13_flat_ends(spark, d):
    """The same errors judged by one graph over flattened facts: by start, by end."""
    return _flattened(spark, d, ("start", "end"))


@query()
def w13_flat_both(spark, d):
    """The same by the middle, and with both ends as facts of their own."""
    return _flattened(spark, d, ("midpoint", "two-point"))


@query()
def w13_missing(spark, d):
    """What no graph of the four can instantiate, for facts of the test part without conflicts."""
    case = _case(spark, d)
    columns = ["s", "r", "o", "t_start", "t_end"]
    asked = case.parts["test"].where("kind = 'valid' and not deleted").select(*columns)
    return du.missing_everywhere(asked, case.offline.unionByName(asked), _sides(spark, d), _duration_scores())


@query()
def w14_duration_graphs(spark, d):
    """Explained share of each of the four duration graphs."""
    return spark.createDataFrame(du.explained_share_by_graph(_sides(spark, d)), "graph string, explained_share double")


_FLAT = {"start": "SELECT 'start' AS how, s, r, o, t_start AS t FROM facts", "end": "SELECT 'end', s, r, o, t_end FROM facts", "midpoint": "SELECT 'midpoint', s, r, o, (t_start + t_end) // 2 FROM facts", "two-point": "SELECT 'two-point', s, 'start:' || r, o, t_start FROM facts UNION ALL SELECT 'two-point', s, 'end:' || r, o, t_end FROM facts"}


@query(over("validity", "x AS (" + " UNION ALL ".join(_FLAT.values()) + ")", select="SELECT how, count(*) AS n FROM (SELECT DISTINCT * FROM x) GROUP BY how"))
def w14_flattenings(spark, d):
    dfacts = fx.validity(spark, d)
    parts = [du.flatten_duration(dfacts, how).agg(F.count(F.lit(1)).alias("n")).select(F.lit(how).alias("how"), "n") for how in _FLAT]
    out = parts[0]
    for p in parts[1:]:
        out = out.unionByName(p)
    return out


def worked_case(spark: SparkSession) -> tuple[DataFrame, DataFrame]:
    """(history, asked) of the three kinds of errors with invented names: offices follow elections."""
    people = [(f"P{i}", f"L{i % 4}", 10 * i) for i in range(24)]
    rows = []
    for p, land, t in people:
        rows += [(p, "elected", land, t), (p, "office", land, t + 3), (p, "leaves", land, t + 8)]
    rows += [(f"B{i}", "exercise", f"L{i % 4}", 5 * i) for i in range(24)]
    history = spark.createDataFrame([r for r in rows if not (r[0] == "P20" and r[1] == "elected")], "s string, r string, o string, t long")
    asked = spark.createDataFrame([("P23", "exercise", "L3", 300), ("P5", "office", "L1", 300), ("P22", "office", "L2", 223), ("P20", "office", "L0", 203)], "s string, r string, o string, t long")
    return history, asked


@query()
def w15_worked_case(spark, d):
    """A wrong relation, an office long after its election, a sound office, and one whose election is missing."""
    history, asked = worked_case(spark)
    g = build(history, BuildConfig(kinds_known=True, closures=False, horizon=50))
    config = sc.ScoreConfig(K=1, L=1, closures=False)
    trace: list = []
    facts = sc.identified(asked)
    scored = sc.score(facts, history.unionByName(asked), g, config, trace)
    missing = sc.missing_candidates(facts, history, g, trace[0], history).groupBy("s", "o").agg(F.max("r").alias("missing_relation"))
    return scored.join(missing, ["s", "o"], "left").select("s", "r", "o", "t", "ev_static", r6("ev_temporal").alias("ev_temporal"), "n_out", "missing_relation")


@query()
def w15_prompts(spark, d):
    """What would make the wrong relation right."""
    history, asked = worked_case(spark)
    g = build(history, BuildConfig(kinds_known=True, closures=False, horizon=50))
    return sc.fix_prompts(sc.identified(asked), g)


@query()
def missing_facts(spark, d):
    """Facts that the graph expects and the data lacks: the test part of lifecycle, with the deleted facts left out."""
    e, own = exp(spark, d, "lifecycle"), run(spark, d, "lifecycle")
    config = wl.score_config("lifecycle")
    facts = sc.identified(e.parts["test"]["left"])
    history = e.offline.unionByName(e.parts["validation"]["valid"]).unionByName(e.parts["test"]["left"])
    trace, _, _ = sc.walk(facts, history, own.graph, config)
    return sc.missing_candidates(facts, history, own.graph, trace, history, config).drop("fact_id")


@query()
def missing_recovered(spark, d):
    """How many of the deleted facts, and of the confirmations that the data lacks by construction, the candidates name
    (by triple, at most the link's lag tolerance away)."""
    e = exp(spark, d, "lifecycle")
    found = staged(missing_facts(spark, d), "found")
    sales = fx._sales(spark, d).where((7 * F.col("l_orderkey") + F.col("l_linenumber")) % 20 == 0)
    low = e.parts["test"]["valid"].agg(F.min("t")).first()[0]
    never = sales.select(F.col("c").alias("s"), F.lit("confirm").alias("r"), F.col("u").alias("o"), (F.col("ordered") + 2 + F.col("l_orderkey") % 3).alias("t")).where(F.col("t") >= low).distinct().join(e.facts, ["s", "r", "o", "t"], "left_anti")
    parts = []
    for what, gone in (("deleted", e.parts["test"]["gone"]), ("never there", never)):
        near = gone.join(found.select("s", "r", "o", F.col("t").alias("t_found")), ["s", "r", "o"]).where(F.abs(F.col("t") - F.col("t_found")) <= 3).select("s", "r", "o", "t").distinct()
        parts.append(gone.groupBy("r").agg(F.count(F.lit(1)).alias("n")).join(near.groupBy("r").agg(F.count(F.lit(1)).alias("named")), "r", "left").fillna(0).select(F.lit(what).alias("what"), "r", "n", "named"))
    return parts[0].unionByName(parts[1])


@query()
def evidence(spark, d):
    """The links and witnesses behind the scores of all facts of the test part."""
    e, own = exp(spark, d, "lifecycle"), run(spark, d, "lifecycle")
    facts = sc.identified(e.parts["test"]["valid"])
    trace, _, _ = sc.walk(facts, e.facts, own.graph, wl.score_config("lifecycle"))
    return sc.explain(trace, oc.witness_names(e.offline))


@query()
def time_hints(spark, d):
    """Where evidence would put the wrong ticks of the test part."""
    e, g = exp(spark, d, "lifecycle"), graph(spark, d, "lifecycle")
    return sc.time_prompts(sc.identified(e.parts["test"]["time"]), e.facts, g, wl.score_config("lifecycle")).drop("fact_id")


@query()
def w16_refresh(spark, d):
    """Rebuilding by accumulated error, after a fixed time, or never, over replayed clicks."""
    facts = staged(fx.clicks(spark, d), "facts")
    offline, rest = facts.where("t < 360"), facts.where("t >= 360")
    config = wl.build_config("clicks", kinds_known=True, closures=False)
    start = online.start_state(offline, config)

    names = ("error", "every_n_ticks", "never")
    policies = [OnlineConfig(refresh=p, refresh_every=96, monitor="per_slice", th_static=1.0, th_temporal=1e9) for p in names]
    states = online.replay_policies(rest, replace(start, log=[]), wl.score_config("clicks", closures=False, K=0), policies, [360, 480, 720])
    rows = [(p, sum(x["rebuilt"] for x in s.log), round(sum(x["bits"] for x in s.log), 3), sum(x["facts"] for x in s.log)) for p, s in zip(names, states, strict=True)]
    return spark.createDataFrame(rows, "policy string, rebuilds long, error_bits double, facts long")


# ---- streams ----------------------------------------------------------------------------------------------------


@query("SELECT CAST(epoch(time_bucket(INTERVAL '6 hours', ts, TIMESTAMP '1970-01-01')) AS BIGINT) AS start, event_type, count(*) AS n FROM events GROUP BY ALL")
def stream_tumbling(spark, d):
    return online.drained(online.tumbling(online.event_stream(spark, d)), "tumbling", "complete")


@query("SELECT start, event_type, count(*) AS n FROM (SELECT CAST(epoch(time_bucket(INTERVAL '12 hours', ts, TIMESTAMP '1970-01-01')) AS BIGINT) - k * 43200 AS start, event_type FROM events, (SELECT unnest([0, 1]) AS k)) GROUP BY ALL")
def stream_sliding(spark, d):
    return online.drained(online.sliding(online.event_stream(spark, d)), "sliding", "complete")


@query("WITH g AS (SELECT user_id, ts, CASE WHEN ts - lag(ts) OVER (PARTITION BY user_id ORDER BY ts, event_id) < INTERVAL '2 hours' THEN 0 ELSE 1 END AS new FROM events), s AS (SELECT user_id, ts, sum(new) OVER (PARTITION BY user_id ORDER BY ts ROWS UNBOUNDED PRECEDING) AS k FROM g) SELECT CAST(floor(epoch(min(ts))) AS BIGINT) AS start, user_id, count(*) AS n FROM s GROUP BY user_id, k")
def stream_session(spark, d):
    return online.drained(online.sessions(online.event_stream(spark, d)), "sessions", "complete")


@query("SELECT event_id, user_id FROM events")
def stream_dedup(spark, d):
    """Every event delivered twice and kept once: repeats are known within the watermark, no other step removes them."""
    events = online.event_stream(spark, d)
    twice = events.withColumn("_copy", F.explode(F.array(F.lit(0), F.lit(1)))).drop("_copy")
    return online.drained(online.once(twice).select("event_id", "user_id"), "dedup")


@query("WITH m AS (SELECT epoch(min(ts)) AS lo, epoch(max(ts)) AS hi FROM events), x AS (SELECT CAST(floor(epoch(ts) / 21600) * 21600 AS BIGINT) AS start FROM events, m WHERE epoch(ts) >= floor((lo + hi) / 2)) SELECT start, count(*) AS n FROM x, m WHERE start + 21600 <= hi - 3600 GROUP BY start")
def stream_late_drop(spark, d):
    """The later half of the events first, the earlier half after it: what comes behind the watermark is dropped."""
    return online.late_dropped(spark, d)


@query(over("clicks", PATTERNS, select="SELECT f.s, f.r, f.o, CAST(f.t AS BIGINT) AS t, round(1.0 / n, 9) AS score_static FROM facts f JOIN pats p ON substr(f.s, 1, 1) = cs AND f.r = p.r AND substr(f.o, 1, 1) = co"))
def stream_score(spark, d):
    """Facts of a stream scored batch by batch against a graph of all patterns."""
    facts = fx.clicks(spark, d)
    model = all_patterns(facts, cats.by_kind(facts))
    arriving = fx.click_facts(online.event_stream(spark, d))
    return online.scored_stream(arriving, model).select("s", "r", "o", "t", F.round("score_static", 9).alias("score_static")).distinct()


@query("SELECT a.event_id AS i1, b.event_id AS i2, a.event_type AS head, b.event_type AS tail FROM events a JOIN events b ON a.user_id = b.user_id AND b.ts > a.ts AND b.ts <= a.ts + INTERVAL '6 hours'")
def stream_chain_join(spark, d):
    return online.drained(online.chain_join(online.event_stream(spark, d)), "chain-join")


@query(over("clicks", select="SELECT s, o, CAST(max(t) AS BIGINT) AS last, count(*) AS n FROM facts GROUP BY s, o"))
def stream_pair_state(spark, d):
    """State kept by pair across batches; the last state of each pair is what a batch aggregate gives.

    Facts are sets: events that give the same fact count once, however far apart they arrive, so no watermark drops any.
    """
    path = online.new_path(spark, "pairs")
    facts = fx.click_facts(online.event_stream(spark, d)).dropDuplicates(["s", "r", "o", "t"])
    query_ = online.pair_state(facts.select("s", "o", "t")).writeStream.outputMode("update").foreachBatch(lambda df, i: df.write.mode("overwrite").parquet(f"{path}/batch={i}")).option("checkpointLocation", online.new_path(spark, "pairs-state")).trigger(availableNow=True).start()
    query_.awaitTermination()
    out = spark.read.parquet(path)
    return out.groupBy("s", "o").agg(F.max("last").alias("last"), F.max("n").alias("n"))


@query()
def stream_monitor(spark, d):
    """The whole online loop on a stream of clicks after the first half: score, keep, update, monitor."""
    facts = fx.clicks(spark, d)
    config = wl.build_config("clicks", kinds_known=True, closures=False)
    state = online.start_state(facts.where("t < 360"), config)
    stream = fx.click_facts(online.event_stream(spark, d)).where("t >= 360")
    path = online.new_path(spark, "scored")
    online.run_online(stream, state, wl.score_config("clicks", closures=False, K=0), OnlineConfig(refresh="never", th_static=1.0, th_temporal=1e9), path)
    return spark.read.parquet(path).groupBy("verdict").agg(F.count(F.lit(1)).alias("n"))


__all__ = ["code_bits", "exp", "graph", "held", "map_patterns", "worked_case"]
