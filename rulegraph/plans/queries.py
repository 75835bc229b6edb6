"""Queries of the engine by name, each with the SQL that gives the same rows where SQL can."""

from __future__ import annotations

from collections.abc import Callable

import pandas as pd
from pyspark.sql import DataFrame, SparkSession, Window
from pyspark.sql import functions as F

from ..functions.mdl import code_bits, error_bits, f_beta, log2_choose
from ..operators import categories as cats
from ..operators import evaluation as ev
from ..operators import occurrences as oc
from ..sources import facts as fx
from ..storage import staged
from .oracles import FACTS, KINDS, PATTERNS, choose, draw, over

Query = Callable[[SparkSession, str], DataFrame]
QUERIES: dict[str, Query] = {}
ORACLES: dict[str, str] = {}


def query(oracle: str | None = None, name: str | None = None):
    def add(f: Query) -> Query:
        key = name or f.__name__
        QUERIES[key] = f
        if oracle:
            ORACLES[key] = oracle
        return f

    return add


def r6(c):
    return F.round(c, 6)


def kinds(c: str):
    return F.substring(c, 1, 1)


# ---- sources -------------------------------------------------------------------------------------------

for _name, _make in fx.FIXTURES.items():
    query(over(_name, select="SELECT s, r, o, CAST(t AS BIGINT) AS t FROM facts"), f"facts_{_name}")(_make)


@query(over("validity", select="SELECT s, r, o, CAST(t_start AS BIGINT) AS t_start, CAST(t_end AS BIGINT) AS t_end FROM facts"))
def facts_validity(spark, d):
    return fx.validity(spark, d)


@query("SELECT o_orderkey, o_custkey, o_totalprice FROM orders WHERE o_totalprice > 200000 AND o_orderstatus = 'F'")
def scan_pruned(spark, d):
    return fx.table(spark, d, "orders").where((F.col("o_totalprice") > 200000) & (F.col("o_orderstatus") == "F")).select("o_orderkey", "o_custkey", "o_totalprice")


_TABLES = ("region", "nation", "customer", "supplier", "part", "orders", "lineitem", "events", "documents", "embeddings", "pages", "benchmark", "labels", "conversations")


@query(" UNION ALL ".join(f"SELECT '{t}' AS name, count(*) AS n FROM {t}" for t in _TABLES))
def scan_parquet(spark, d):
    parts = [fx.table(spark, d, t).agg(F.count(F.lit(1)).alias("n")).select(F.lit(t).alias("name"), "n") for t in _TABLES]
    out = parts[0]
    for p in parts[1:]:
        out = out.unionByName(p)
    return out


@query(over("clicks", select="SELECT s, r, o, CAST(t AS BIGINT) AS t FROM facts"))
def text_round_trip(spark, d):
    """Facts through a tab-separated text file and back."""
    from ..storage import new_path

    path = new_path(spark, "triples")
    fx.clicks(spark, d).write.csv(path, sep="\t")
    return fx.read_triples(spark, path)


@query(over("trade", select="SELECT CAST(floor(t / 30.0) AS BIGINT) AS t_bucket, count(*) AS n FROM facts WHERE t < 300 GROUP BY 1"))
def history_pruned(spark, d):
    """History partitioned by time bucket; the filter prunes folders."""
    from ..storage import new_path

    path = new_path(spark, "history")
    fx.write_history(fx.trade(spark, d), path, 30)
    return spark.read.parquet(path).where("t_bucket < 10").groupBy(F.col("t_bucket").cast("long").alias("t_bucket")).agg(F.count(F.lit(1)).alias("n"))


@query(over("lifecycle", select="SELECT count(*) AS n FROM facts"))
def names_round_trip(spark, d):
    """Encoded facts joined back with the dictionary give as many facts."""
    facts = fx.lifecycle(spark, d)
    names = fx.dictionary(facts)
    one = lambda c, rel: names.where(F.col("is_relation") == rel).select(F.col("id").alias(c), F.col("name").alias(f"{c}_name"))
    back = fx.encode(facts).join(one("s", False), "s").join(one("r", True), "r").join(one("o", False), "o")
    return back.select("s_name", "r_name", "o_name", "t").distinct().agg(F.count(F.lit(1)).alias("n"))


# ---- projections, filters, scalars -----------------------------------------------------------------------


@query(over("trade", select="SELECT DISTINCT s, r, o FROM facts"))
def proj_triple(spark, d):
    return fx.trade(spark, d).select("s", "r", "o").distinct()


@query(over("lifecycle", select="SELECT s, r, o, CAST(t AS BIGINT) AS t FROM facts WHERE t <= 1400"))
def filter_offline(spark, d):
    return fx.lifecycle(spark, d).where("t <= 1400")


@query(over("lifecycle", select="SELECT s, r, o, CAST(t AS BIGINT) AS t FROM facts WHERE t BETWEEN 1401 AND 1420 AND r = 'confirm'"))
def filter_tail_window(spark, d):
    return fx.lifecycle(spark, d).where("t between 1401 and 1420 and r = 'confirm'")


@query("SELECT event_id, CAST(json_extract_string(props, '$.k') AS BIGINT) AS k FROM events")
def props_key(spark, d):
    return fx.table(spark, d, "events").select("event_id", F.get_json_object("props", "$.k").cast("long").alias("k"))


@query("SELECT page_id, regexp_extract(url, '^[a-z]+://([^/]+)', 1) AS host, regexp_extract(url, '^[a-z]+://[^/]+(/[^?#]*)?', 1) AS path FROM pages")
def host_path(spark, d):
    return fx.table(spark, d, "pages").select("page_id", F.regexp_extract("url", "^[a-z]+://([^/]+)", 1).alias("host"), F.regexp_extract("url", "^[a-z]+://[^/]+(/[^?#]*)?", 1).alias("path"))


@query("""SELECT page_id, count(*) AS n_hrefs FROM (SELECT page_id, unnest(regexp_extract_all(html, 'href="([^"]*)"', 1)) AS h FROM pages) GROUP BY 1""")
def hrefs(spark, d):
    found = fx.table(spark, d, "pages").select("page_id", F.explode(F.regexp_extract_all("html", F.lit('href="([^"]*)"'), 1)).alias("h"))
    return found.groupBy("page_id").agg(F.count(F.lit(1)).alias("n_hrefs"))


@query("SELECT c_custkey, 'C' || lpad(CAST(c_custkey AS VARCHAR), 8, '0') || '@' || c_mktsegment AS label FROM customer")
def entity_label(spark, d):
    return fx.table(spark, d, "customer").select("c_custkey", F.concat(F.lit("C"), F.lpad(F.col("c_custkey").cast("string"), 8, "0"), F.lit("@"), "c_mktsegment").alias("label"))


@query(f"SELECT o_orderkey, {draw('d', 'o_orderkey')} AS d FROM orders")
def md5_draws(spark, d):
    return fx.table(spark, d, "orders").select("o_orderkey", ev.draw("d", "o_orderkey").alias("d"))


@query(f"SELECT o_orderkey FROM orders WHERE {draw('sample', 'o_orderkey')} < {int(0.1 * 16**8)}")
def hash_sample(spark, d):
    return fx.table(spark, d, "orders").where(ev.draw("sample", "o_orderkey") < int(0.1 * 16**8)).select("o_orderkey")


@query("SELECT o_orderkey, CAST(date_diff('day', DATE '1995-01-01', CAST(o_orderdate AS DATE)) AS BIGINT) AS tick FROM orders")
def tick_day(spark, d):
    return fx.table(spark, d, "orders").select("o_orderkey", fx.day("o_orderdate").alias("tick"))


@query("SELECT event_id, CAST(floor((epoch(ts) - epoch(TIMESTAMP '2024-01-01')) / 3600) AS BIGINT) AS tick FROM events")
def tick_hour(spark, d):
    return fx.table(spark, d, "events").select("event_id", fx.hour("ts").alias("tick"))


@query("SELECT o_orderkey, CAST((year(o_orderdate) - 1995) * 12 + month(o_orderdate) - 1 AS BIGINT) AS tick FROM orders")
def tick_month(spark, d):
    return fx.table(spark, d, "orders").select("o_orderkey", fx.month("o_orderdate").alias("tick"))


@query(over("validity", select="SELECT r, CAST(sum(t_end - t_start) AS BIGINT) AS days, count(*) AS n FROM facts GROUP BY r"))
def span_days(spark, d):
    return fx.validity(spark, d).groupBy("r").agg(F.sum(F.col("t_end") - F.col("t_start")).alias("days"), F.count(F.lit(1)).alias("n"))


@query(f"SELECT p_partkey, round({choose('p_partkey + 60', 'p_size')}, 6) AS bits FROM part")
def log2_choose_values(spark, d):
    return fx.table(spark, d, "part").select("p_partkey", r6(log2_choose(F.col("p_partkey") + 60, F.col("p_size"))).alias("bits"))


@query(over("trade", select="SELECT r, round(-log2(count(*) / (SELECT count(*) FROM facts)), 6) AS bits FROM facts GROUP BY r"))
def code_bits_relations(spark, d):
    facts = fx.trade(spark, d)
    total = facts.agg(F.count(F.lit(1)).alias("all"))
    return facts.groupBy("r").agg(F.count(F.lit(1)).alias("n")).join(F.broadcast(total)).select("r", r6(code_bits("n", "all")).alias("bits"))


# ---- joins ------------------------------------------------------------------------------------------------


@query(over("trade", PATTERNS, select="SELECT s, f.r, o, CAST(t AS BIGINT) AS t, n AS n_assert FROM facts f JOIN pats p ON substr(s, 1, 1) = cs AND f.r = p.r AND substr(o, 1, 1) = co"))
def map_patterns(spark, d):
    """Every fact with its patterns' assertion counts, kinds as categories."""
    from .build import map_patterns as mapped
    from .build import pattern_counts as counted

    facts = fx.trade(spark, d)
    by_kind = cats.by_kind(facts)
    return mapped(facts, by_kind).join(counted(facts, by_kind), ["cs", "r", "co"]).select("s", "r", "o", "t", "n_assert")


@query(over("trade", select="SELECT s, r, o, CAST(t AS BIGINT) AS t, c_name AS name FROM facts JOIN customer ON s = 'C' || c_custkey"))
def fact_with_names(spark, d):
    names = fx.table(spark, d, "customer").select(fx.named("C", "c_custkey").alias("s"), F.col("c_name").alias("name"))
    return fx.trade(spark, d).join(names, "s").select("s", "r", "o", "t", "name")


_CHAIN = """chain AS (SELECT a.s, a.o, a.r AS r_head, b.r AS r_tail, b.t - a.t AS lag FROM facts a JOIN facts b ON a.s = b.s AND a.o = b.o
  AND (a.t < b.t OR (a.t = b.t AND a.r < b.r)) AND b.t - a.t <= 20)"""


@query(over("lifecycle", _CHAIN, select="SELECT r_head, r_tail, count(*) AS n FROM chain GROUP BY ALL"))
def chain_pairs(spark, d):
    """Ordered pairs of one entity pair within 20 days, by relation."""
    return oc.chain_pairs(fx.lifecycle(spark, d), 20).groupBy("r_head", "r_tail").agg(F.count(F.lit(1)).alias("n"))


@query(over("lifecycle", "seq AS (SELECT r AS r_tail, lag(r) OVER w AS r_head, t - lag(t) OVER w AS l FROM facts WINDOW w AS (PARTITION BY s, o ORDER BY t, r))", select="SELECT r_head, r_tail, count(*) AS n FROM seq WHERE r_head IS NOT NULL AND l <= 20 GROUP BY ALL"))
def chain_adjacent(spark, d):
    return oc.chain_pairs(fx.lifecycle(spark, d), 20, "adjacent").groupBy("r_head", "r_tail").agg(F.count(F.lit(1)).alias("n"))


@query(over("lifecycle", _CHAIN, select="SELECT r_head, r_tail, CAST(lag AS BIGINT) AS lag, count(*) AS cnt FROM chain GROUP BY ALL"))
def lag_histogram(spark, d):
    return oc.chain_pairs(fx.lifecycle(spark, d), 20).groupBy("r_head", "r_tail", "lag").agg(F.count(F.lit(1)).alias("cnt"))


_HALF = "half AS (SELECT o AS leaf, s AS corner, r, 1 AS d, t FROM facts UNION ALL SELECT s, o, r, 0, t FROM facts)"


@query(over("lifecycle", _HALF, select="SELECT a.r AS r1, b.r AS r2, count(*) AS n FROM half a JOIN half b ON a.corner = b.corner AND a.leaf < b.leaf AND abs(a.t - b.t) <= 1 WHERE a.r IN ('want', 'stock') AND b.r IN ('want', 'stock') GROUP BY ALL"))
def cooccur_window(spark, d):
    """Two facts at one corner at most a day apart: an equality join on day buckets."""
    half = oc.half_edges(fx.lifecycle(spark, d).where("r in ('want', 'stock')"))
    one = half.select("corner", F.col("leaf").alias("x"), F.col("r").alias("r1"), F.col("t").alias("t1"), F.col("t").alias("b"))
    two = half.select("corner", F.col("leaf").alias("y"), F.col("r").alias("r2"), F.col("t").alias("t2"), F.explode(F.array(F.col("t") - 1, F.col("t"), F.col("t") + 1)).alias("b"))
    return one.join(two, ["corner", "b"]).where("x < y").groupBy("r1", "r2").agg(F.count(F.lit(1)).alias("n"))


_LATEST = """pairs AS (SELECT s, o, r, t FROM facts),
seen AS (SELECT f.s, f.o, f.r, f.t, h.r AS r_head, max(h.t) AS t_seen FROM facts f JOIN pairs h ON f.s = h.s AND f.o = h.o AND h.t < f.t GROUP BY ALL)"""


@query(over("lifecycle", _LATEST, select="SELECT r_head, r, CAST(t - t_seen AS BIGINT) AS lag, count(*) AS n FROM seen GROUP BY ALL"))
def latest_witness(spark, d):
    """The latest earlier fact of each relation in the pair: an as-of join by a carried value."""
    facts = staged(fx.lifecycle(spark, d), "facts")
    names = sorted(x["r"] for x in facts.select("r").distinct().collect())  # a closed set
    seen = oc.earlier_chains(facts, None, latest=True, relations=names)
    rel = facts.select("r").distinct().select(F.xxhash64(F.lit("chain"), "r").alias("wid"), F.col("r").alias("r_head"))
    return seen.join(F.broadcast(rel), "wid").groupBy("r_head", "r", "lag").agg(F.count(F.lit(1)).alias("n"))


@query(over("lifecycle", "legs AS (SELECT DISTINCT a.s AS c, b.s AS u, greatest(a.t, b.t) AS at_ FROM facts a JOIN facts b ON a.o = b.o AND a.r = 'want' AND b.r = 'stock' AND abs(a.t - b.t) <= 1)", "near AS (SELECT c, u, at_, (SELECT min(t) FROM facts f WHERE f.s = c AND f.o = u AND f.r = 'request' AND f.t >= at_) AS t FROM legs)", select="SELECT CAST(t - at_ AS BIGINT) AS lag, count(*) AS n FROM near WHERE t IS NOT NULL AND t - at_ <= 20 GROUP BY ALL"))
def nearest_close(spark, d):
    """The next request after a want and a stock met at a part: an as-of join forward."""
    facts = fx.lifecycle(spark, d)
    want = facts.where("r = 'want'").select(F.col("s").alias("c"), "o", F.col("t").alias("t1"), F.col("t").alias("b"))
    stock = facts.where("r = 'stock'").select(F.col("s").alias("u"), "o", F.col("t").alias("t2"), F.explode(F.array(F.col("t") - 1, F.col("t"), F.col("t") + 1)).alias("b"))
    legs = want.join(stock, ["o", "b"]).select("c", "u", F.greatest("t1", "t2").alias("at")).distinct()
    asks = legs.select("c", "u", "at", F.lit(None).cast("long").alias("t"), F.lit(1).alias("ask"))
    gets = facts.where("r = 'request'").select(F.col("s").alias("c"), F.col("o").alias("u"), F.col("t").alias("at"), "t", F.lit(0).alias("ask"))
    order = Window.partitionBy("c", "u").orderBy("at", F.desc("ask")).rowsBetween(Window.currentRow, Window.unboundedFollowing)
    found = asks.unionByName(gets).withColumn("next", F.first("t", True).over(order)).where("ask = 1 and next is not null and next - at <= 20")
    return found.groupBy((F.col("next") - F.col("at")).alias("lag")).agg(F.count(F.lit(1)).alias("n"))


@query(over("lifecycle", _CHAIN, "h AS (SELECT r_head, r_tail, lag, count(*) AS cnt FROM chain GROUP BY ALL)", select="SELECT a.r_head, a.r_tail, CAST(a.lag AS BIGINT) AS lag, CAST(sum(b.cnt) AS BIGINT) AS near FROM h a JOIN h b ON a.r_head = b.r_head AND a.r_tail = b.r_tail AND abs(a.lag - b.lag) <= 2 GROUP BY ALL"))
def lag_overlap(spark, d):
    """Kept lags near each lag: the table that scores look lags up in."""
    from ..operators.scoring import near_table

    h = oc.chain_pairs(fx.lifecycle(spark, d), 20).groupBy("r_head", "r_tail", "lag").agg(F.count(F.lit(1)).alias("cnt")).withColumn("cand", F.xxhash64("r_head", "r_tail"))
    return h.join(near_table(h, 2), ["cand", "lag"]).select("r_head", "r_tail", "lag", "near")


@query(over("lifecycle", select="SELECT e, min(t) AS first_t FROM (SELECT s AS e, t FROM facts UNION ALL SELECT o, t FROM facts) GROUP BY e HAVING min(t) > 1400"))
def unseen_entities(spark, d):
    facts = fx.lifecycle(spark, d)
    ends = facts.select(F.col("s").alias("e"), "t").unionByName(facts.select(F.col("o").alias("e"), "t"))
    late, early = ends.where("t > 1400"), ends.where("t <= 1400").select("e")
    return late.join(early, "e", "left_anti").groupBy("e").agg(F.min("t").alias("first_t"))


@query(over("lifecycle", "early AS MATERIALIZED (SELECT DISTINCT s, r, o FROM facts WHERE t <= 2000)", select="SELECT a.s, a.r, a.o, CAST(a.t AS BIGINT) AS t FROM facts a ANTI JOIN early b ON a.s = b.s AND a.r = b.r AND a.o = b.o WHERE a.t > 2000"))
def not_in_facts(spark, d):
    facts = fx.lifecycle(spark, d)
    return facts.where("t > 2000").join(facts.where("t <= 2000").select("s", "r", "o").distinct(), ["s", "r", "o"], "left_anti").select("s", "r", "o", "t")


@query(over("trade", "rels AS (SELECT DISTINCT substr(s, 1, 1) AS cs, r, substr(o, 1, 1) AS co, t < 1500 AS early FROM facts)", select="SELECT cs, r, co FROM rels GROUP BY ALL HAVING NOT bool_or(early)"))
def absent_patterns(spark, d):
    facts = fx.trade(spark, d).select(kinds("s").alias("cs"), "r", kinds("o").alias("co"), "t")
    return facts.where("t >= 1500").select("cs", "r", "co").distinct().join(facts.where("t < 1500").select("cs", "r", "co").distinct(), ["cs", "r", "co"], "left_anti")


# ---- aggregates ---------------------------------------------------------------------------------------------


@query(over("trade", PATTERNS, select="SELECT cs, r, co, n AS n_assert FROM pats"))
def pattern_counts(spark, d):
    from .build import pattern_counts as counted

    facts = fx.trade(spark, d)
    return counted(facts, cats.by_kind(facts))


@query(over("clicks", select="SELECT r, count(*) AS n, count(DISTINCT s) AS subjects FROM facts GROUP BY r"))
def relation_freq(spark, d):
    return fx.clicks(spark, d).groupBy("r").agg(F.count(F.lit(1)).alias("n"), F.countDistinct("s").alias("subjects"))


@query(over("trade", KINDS, select="SELECT substr(e, 1, 1) AS cat, count(*) AS n FROM ents GROUP BY 1"))
def category_freq(spark, d):
    found = cats.by_kind(fx.trade(spark, d)).of_entities()
    return found.groupBy("cat").agg(F.count(F.lit(1)).alias("n"))


@query(over("trade", "c AS (SELECT substr(s, 1, 1) AS cs, r, substr(o, 1, 1) AS co, s, count(*) AS n FROM facts GROUP BY ALL)", select="SELECT cs, r, co, round(sum(n) * log2(sum(n)) - sum(n * log2(n)), 4) AS bits FROM c GROUP BY ALL"))
def entropy_subject(spark, d):
    """Bits of subjects' codes among each pattern's assertions, in closed form."""
    c = fx.trade(spark, d).groupBy(kinds("s").alias("cs"), "r", kinds("o").alias("co"), "s").agg(F.count(F.lit(1)).alias("n"))
    g = c.groupBy("cs", "r", "co").agg(F.sum("n").alias("a"), F.sum(F.col("n") * F.log2(F.col("n").cast("double"))).alias("b"))
    return g.select("cs", "r", "co", F.round(F.col("a") * F.log2(F.col("a").cast("double")) - F.col("b"), 4).alias("bits"))


@query(over("lifecycle", select="SELECT CAST(t AS BIGINT) AS t, count(*) AS n_facts, count(DISTINCT s) AS n_subjects FROM facts GROUP BY t"))
def slice_counts(spark, d):
    return fx.lifecycle(spark, d).groupBy("t").agg(F.count(F.lit(1)).alias("n_facts"), F.countDistinct("s").alias("n_subjects"))


@query(over("lifecycle", KINDS, "z AS (SELECT (SELECT count(*) FROM ents) * (SELECT count(*) FROM ents) * (SELECT count(DISTINCT r) FROM facts) AS space)", "g AS (SELECT t, count(*) AS u FROM facts GROUP BY t)", select=f"SELECT CAST(t AS BIGINT) AS t, round({choose('space', 'u')}, 4) AS bits FROM g, z"))
def error_bits_empty(spark, d):
    """Error bits of each tick when nothing is explained."""
    facts = fx.lifecycle(spark, d)
    ends = facts.select(F.col("s").alias("e")).unionByName(facts.select(F.col("o").alias("e"))).agg(F.countDistinct("e")).first()[0]
    rels = facts.agg(F.countDistinct("r")).first()[0]
    return facts.groupBy("t").agg(F.count(F.lit(1)).alias("u")).select("t", F.round(error_bits(float(ends) ** 2 * rels, F.lit(0), "u"), 4).alias("bits"))


@query(over("trade", KINDS, select="SELECT (SELECT count(*) FROM ents) AS entities, count(DISTINCT r) AS relations, count(DISTINCT t) AS ticks, count(*) AS facts FROM facts"))
def entity_count(spark, d):
    return _stats(fx.trade(spark, d))


def _stats(facts: DataFrame) -> DataFrame:
    ends = facts.select(F.col("s").alias("e")).unionByName(facts.select(F.col("o").alias("e"))).distinct().agg(F.count(F.lit(1)).alias("entities"))
    rest = facts.agg(F.countDistinct("r").alias("relations"), F.countDistinct("t").alias("ticks"), F.count(F.lit(1)).alias("facts"))
    return ends.join(rest).select("entities", "relations", "ticks", "facts")


@query()
def approx_entities(spark, d):
    facts = fx.trade(spark, d)
    return facts.agg(F.approx_count_distinct("s").alias("subjects"), F.approx_count_distinct("o").alias("objects"))


@query()
def approx_topk_patterns(spark, d):
    return fx.trade(spark, d).select(F.concat_ws(" ", kinds("s"), "r", kinds("o")).alias("p")).agg(F.expr("approx_top_k(p, 10)").alias("top")).select(F.explode("top").alias("x")).select("x.item", "x.count")


@query(over("lifecycle", f"x AS (SELECT CAST(floor(t / 365.0) AS BIGINT) AS year, CAST(floor(t / 30.0) AS BIGINT) AS month, CASE WHEN EXISTS (SELECT 1 FROM facts h WHERE h.s = f.s AND h.o = f.o AND h.t < f.t AND f.t - h.t <= 30) THEN 1 ELSE 0 END AS e FROM facts f)", select="SELECT year, month, count(*) AS n_facts, CAST(sum(e) AS BIGINT) AS n_explained FROM x GROUP BY ROLLUP (year, month)"))
def explained_rollup(spark, d):
    """Explained facts by year and month: all chain links of 30 days, kinds as categories."""
    from ..operators.updating import explained_ticks
    from .experiments import all_links

    facts = staged(fx.lifecycle(spark, d), "facts")
    ticks = explained_ticks(facts, None, all_links(facts, 30, space=True), 30)
    own = ticks.withColumn("year", F.floor(F.col("t") / 365)).withColumn("month", F.floor(F.col("t") / 30))
    return own.rollup("year", "month").agg(F.sum("n_facts").alias("n_facts"), F.sum("n_explained").alias("n_explained"))


@query(over("clicks", "z AS (SELECT min(t) AS low, max(t) - min(t) + 1 AS span FROM facts)", f"ch AS (SELECT *, {draw('time2', 's', 'r', 'o', 't')} AS d FROM facts WHERE {draw('time', 's', 'r', 'o', 't')} < {int(0.15 * 16**8)})", "made AS (SELECT DISTINCT s, r, o, low + (t - low + span // 4 + d % (span - 2 * (span // 4))) % span AS t FROM ch, z)", f"x AS (SELECT 'time' AS kind, r FROM (SELECT s, r, o, t FROM made EXCEPT SELECT s, r, o, t FROM facts) UNION ALL SELECT 'missing', r FROM facts WHERE {draw('missing', 's', 'r', 'o', 't')} < {int(0.15 * 16**8)})", select="SELECT kind, r, count(*) AS n FROM x GROUP BY CUBE (kind, r)"))
def errors_cube(spark, d):
    """Injected errors by kind and relation, with all subtotals."""
    facts = fx.clicks(spark, d)
    made = ev.inject_time(facts, facts).select(F.lit("time").alias("kind"), "r").unionByName(ev.inject_missing(facts)[1].select(F.lit("missing").alias("kind"), "r"))
    return made.cube("kind", "r").agg(F.count(F.lit(1)).alias("n"))


@query(f"WITH x AS (SELECT CAST(floor(date_diff('day', DATE '1995-01-01', CAST(l_shipdate AS DATE)) / 365.0) AS BIGINT) AS bin, l_linestatus AS side, CASE WHEN l_returnflag = 'R' THEN 1 ELSE 0 END AS label, {draw('score', 'l_orderkey', 'l_linenumber', digits=2)} >= 128 AS hit FROM lineitem), p AS (SELECT bin, side, round(count(*) FILTER (hit AND label = 1) / nullif(count(*) FILTER (hit), 0), 6) AS precision FROM x GROUP BY ALL) SELECT bin, max(precision) FILTER (side = 'F') AS \"F\", max(precision) FILTER (side = 'O') AS \"O\" FROM p GROUP BY bin")
def metric_pivot(spark, d):
    """Precision by year, one column for each line status."""
    lines = fx.table(spark, d, "lineitem").select(ev.draw("score", "l_orderkey", "l_linenumber", digits=2).alias("score"), (F.col("l_returnflag") == "R").cast("int").alias("label"), fx.day("l_shipdate").alias("t"), F.col("l_linestatus").alias("side"))
    parts = [ev.accuracy_over_time(lines.where(F.col("side") == x), 128, 365).select("bin", F.lit(x).alias("side"), r6("precision").alias("precision")) for x in ("F", "O")]
    return parts[0].unionByName(parts[1]).groupBy("bin").pivot("side", ["F", "O"]).agg(F.max("precision"))


# ---- windows --------------------------------------------------------------------------------------------------


@query(over("clicks", select="SELECT s, r, o, CAST(t AS BIGINT) AS t, CAST(row_number() OVER (PARTITION BY s, o ORDER BY t, r) AS INTEGER) AS place FROM facts"))
def pair_sequence(spark, d):
    return oc.pair_sequences(fx.clicks(spark, d)).select("s", "r", "o", "t", F.col("place").cast("int").alias("place"))


@query(over("lifecycle", "n AS (SELECT r, lead(r) OVER (PARTITION BY s, o ORDER BY t, r) AS next FROM facts)", select="SELECT r, next, count(*) AS n FROM n GROUP BY ALL"))
def next_relation(spark, d):
    w = Window.partitionBy("s", "o").orderBy("t", "r")
    return fx.lifecycle(spark, d).select("r", F.lead("r").over(w).alias("next")).groupBy("r", "next").agg(F.count(F.lit(1)).alias("n"))


@query(over("clicks", "g AS (SELECT t - lag(t) OVER (PARTITION BY s ORDER BY t, r, o) AS gap FROM facts)", select="SELECT CAST(gap AS BIGINT) AS gap, count(*) AS n FROM g GROUP BY ALL"))
def gap_prev(spark, d):
    w = Window.partitionBy("s").orderBy("t", "r", "o")
    return fx.clicks(spark, d).select((F.col("t") - F.lag("t").over(w)).alias("gap")).groupBy("gap").agg(F.count(F.lit(1)).alias("n"))


@query(over("lifecycle", PATTERNS, "ranked AS (SELECT *, row_number() OVER (ORDER BY n DESC, cs || r || co DESC) AS rank FROM pats)", "c AS (SELECT t, rank, count(*) AS claim FROM facts JOIN ranked ON substr(s, 1, 1) = cs AND facts.r = ranked.r AND substr(o, 1, 1) = co GROUP BY ALL)", select="SELECT CAST(t AS BIGINT) AS t, rank, claim, CAST(coalesce(sum(claim) OVER (PARTITION BY t ORDER BY rank ROWS BETWEEN UNBOUNDED PRECEDING AND 1 PRECEDING), 0) AS BIGINT) AS above FROM c"))
def running_claims(spark, d):
    """What each ranked pattern claims of a tick, and what better ones claim before it: a round of the selection."""
    from ..operators.selection import claims_of

    cells = fx.lifecycle(spark, d).groupBy(kinds("s").alias("cs"), "r", kinds("o").alias("co"), "t").agg(F.count(F.lit(1)).alias("n"))
    own = _ranked(fx.lifecycle(spark, d))
    cover = cells.join(own.select("cs", "r", "co", "rank"), ["cs", "r", "co"]).select("rank", F.xxhash64("cs", "r", "co").alias("cell"), "t", "n")
    return claims_of(cover, own.select("rank", F.lit(True).alias("accepted"))).select("t", "rank", "claim", "above")


def _ranked(facts):
    from ..operators.selection import rank_candidates as ranked

    p = facts.groupBy(kinds("s").alias("cs"), "r", kinds("o").alias("co")).agg(F.count(F.lit(1)).alias("n_assert"))
    return ranked(p.withColumn("cand", F.concat("cs", "r", "co")), "assertions")


@query(over("lifecycle", "c AS (SELECT t, count(*) AS n FROM facts GROUP BY t)", select="SELECT CAST(t AS BIGINT) AS t, n, CAST(sum(n) OVER (ORDER BY t) AS BIGINT) AS total FROM c"))
def running_total(spark, d):
    """A global running sum by range partitions: no window holds all rows."""
    from ..operators.running import running_sums

    c = fx.lifecycle(spark, d).groupBy("t").agg(F.count(F.lit(1)).alias("n"))
    return running_sums(c, ["t"], {"total": "n"})


@query(over("clicks", "c AS (SELECT CAST(floor(t / 24.0) AS BIGINT) AS day, r, count(*) AS n FROM facts GROUP BY ALL)", select="SELECT day, r, n, round(avg(n) OVER (PARTITION BY r ORDER BY day ROWS 6 PRECEDING), 6) AS mean7 FROM c"))
def slice_moving(spark, d):
    c = fx.clicks(spark, d).groupBy(F.floor(F.col("t") / 24).alias("day"), "r").agg(F.count(F.lit(1)).alias("n"))
    return c.withColumn("mean7", r6(F.avg("n").over(Window.partitionBy("r").orderBy("day").rowsBetween(-6, 0))))


@query(over("trade", PATTERNS, select="SELECT cs, r, co, n AS n_assert, row_number() OVER (ORDER BY n DESC, cs || r || co DESC) AS rank FROM pats"))
def rank_candidates(spark, d):
    """Ranks by range partitions: no window holds all candidates."""
    return _ranked(fx.trade(spark, d)).select("cs", "r", "co", "n_assert", "rank")


_SCORED = f"scored AS (SELECT {draw('score', 'l_orderkey', 'l_linenumber', digits=2)} AS score, CASE WHEN l_returnflag = 'R' THEN 1 ELSE 0 END AS label FROM lineitem)"


@query("WITH " + _SCORED + ", c AS (SELECT score, sum(label) AS p, count(*) - sum(label) AS n FROM scored GROUP BY score), w AS (SELECT score, sum(p) OVER (ORDER BY score DESC) AS tp, sum(n) OVER (ORDER BY score DESC) AS fp, sum(p) OVER () AS total FROM c) SELECT CAST(score AS BIGINT) AS score, CAST(tp AS BIGINT) AS tp, CAST(fp AS BIGINT) AS fp, round(tp / (tp + fp), 6) AS precision, round(tp / total, 6) AS recall FROM w")
def pr_curve(spark, d):
    return ev.pr_curve(_scored(spark, d)).select("score", "tp", "fp", r6("precision").alias("precision"), r6("recall").alias("recall"))


def _scored(spark, d):
    lines = fx.table(spark, d, "lineitem")
    return lines.select(ev.draw("score", "l_orderkey", "l_linenumber", digits=2).alias("score"), (F.col("l_returnflag") == "R").cast("int").alias("label"))


@query("WITH " + _SCORED + ", c AS (SELECT score, sum(label) AS p, count(*) - sum(label) AS n FROM scored GROUP BY score), w AS (SELECT p, sum(p) OVER (ORDER BY score DESC) AS tp, sum(n) OVER (ORDER BY score DESC) AS fp, sum(p) OVER () AS total FROM c) SELECT round(sum(tp / (tp + fp) * p / total), 6) AS pr_auc FROM w")
def pr_auc(spark, d):
    return spark.createDataFrame([(round(ev.area_under_pr(ev.pr_curve(_scored(spark, d))), 6),)], "pr_auc double")


@query("WITH " + _SCORED + ", x AS (SELECT th, count(*) FILTER (score >= th AND label = 1) AS tp, count(*) FILTER (score >= th AND label = 0) AS fp, count(*) FILTER (score < th AND label = 1) AS fn FROM scored, (SELECT unnest([64, 128, 192]) AS th) GROUP BY th) SELECT CAST(th AS BIGINT) AS th, round(1.25 * tp / (1.25 * tp + 0.25 * fn + fp), 6) AS f05 FROM x")
def f_beta_values(spark, d):
    th = spark.createDataFrame([(64,), (128,), (192,)], "th long")
    x = _scored(spark, d).groupBy("score", "label").agg(F.count(F.lit(1)).alias("n")).join(F.broadcast(th))
    one = lambda cond: F.sum(F.when(cond, F.col("n")).otherwise(0))
    x = x.groupBy("th").agg(one((F.col("score") >= F.col("th")) & (F.col("label") == 1)).alias("tp"), one((F.col("score") >= F.col("th")) & (F.col("label") == 0)).alias("fp"), one((F.col("score") < F.col("th")) & (F.col("label") == 1)).alias("fn"))
    return x.select("th", r6(f_beta(F.col("tp"), F.col("fp"), F.col("fn"))).alias("f05"))


# ---- sort, sets, arrays -------------------------------------------------------------------------------------------


@query(over("lifecycle", _CHAIN, select="SELECT * FROM (SELECT r_head, r_tail, count(*) AS n FROM chain GROUP BY ALL) ORDER BY n DESC, r_head || r_tail DESC LIMIT 3"))
def top_links(spark, d):
    """The cap on candidates: most asserted first."""
    from .build import cap_links

    found = chain_pairs(spark, d).withColumn("cand", F.concat("r_head", "r_tail")).withColumnRenamed("n", "n_assert")
    return cap_links(found, 3).select("r_head", "r_tail", F.col("n_assert").alias("n"))


@query(over("trade", PATTERNS, select="SELECT cs, r, co, n FROM pats ORDER BY n DESC, cs, r, co LIMIT 5"))
def top_patterns(spark, d):
    p = fx.trade(spark, d).groupBy(kinds("s").alias("cs"), "r", kinds("o").alias("co")).agg(F.count(F.lit(1)).alias("n"))
    return p.orderBy(F.desc("n"), "cs", "r", "co").limit(5)


@query(over("trade", PATTERNS, "x AS (SELECT *, row_number() OVER (PARTITION BY cs ORDER BY n DESC, r, co) AS i FROM pats)", select="SELECT cs, r, co, n FROM x WHERE i <= 2"))
def top_per_category(spark, d):
    p = fx.trade(spark, d).groupBy(kinds("s").alias("cs"), "r", kinds("o").alias("co")).agg(F.count(F.lit(1)).alias("n"))
    return p.withColumn("i", F.row_number().over(Window.partitionBy("cs").orderBy(F.desc("n"), "r", "co"))).where("i <= 2").drop("i")


@query("WITH a AS (WITH " + FACTS["clicks"] + " SELECT s, r, o, t FROM facts), b AS (WITH " + FACTS["dialogue"] + " SELECT s, r, o, t FROM facts) SELECT s, r, o, CAST(t AS BIGINT) AS t FROM a UNION SELECT s, r, o, CAST(t AS BIGINT) FROM b")
def facts_union(spark, d):
    return fx.clicks(spark, d).unionByName(fx.dialogue(spark, d)).distinct()


@query(over("lifecycle", select=f"SELECT s, r, o, CAST(t AS BIGINT) AS t FROM facts EXCEPT SELECT s, r, o, t FROM facts WHERE {draw('missing', 's', 'r', 'o', 't')} < {int(0.15 * 16**8)}"))
def facts_minus_deleted(spark, d):
    facts = fx.lifecycle(spark, d)
    return facts.exceptAll(ev.inject_missing(facts)[1])


@query(over("trade", select="SELECT substr(s, 1, 1) AS cs, r, substr(o, 1, 1) AS co FROM facts WHERE t < 1000 INTERSECT SELECT substr(s, 1, 1), r, substr(o, 1, 1) FROM facts WHERE t >= 1000"))
def pattern_overlap(spark, d):
    p = fx.trade(spark, d).select(kinds("s").alias("cs"), "r", kinds("o").alias("co"), "t")
    return p.where("t < 1000").select("cs", "r", "co").intersect(p.where("t >= 1000").select("cs", "r", "co"))


_SETS = "pairs AS (SELECT s AS e, r FROM facts UNION SELECT o, r FROM facts), sets AS (SELECT e, list_sort(list(DISTINCT r)) AS rels FROM pairs GROUP BY e)"


@query(over("trade", _SETS, select="SELECT array_to_string(rels, ',') AS rels, count(*) AS n_ent FROM sets GROUP BY 1"))
def rel_sets(spark, d):
    """Distinct relation sets and how many entities have them: what categories are learned from."""
    p = cats.profiles_of(cats.entity_profiles(cats.entity_relations(fx.trade(spark, d))))
    return p.select(F.array_join("rels", ",").alias("rels"), "n_ent")


@query(over("trade", _SETS, "one AS (SELECT e, r FROM pairs)", "two AS (SELECT a.e, a.r AS r1, b.r AS r2 FROM one a JOIN one b ON a.e = b.e AND a.r < b.r)", "three AS (SELECT a.e, a.r1, a.r2, b.r AS r3 FROM two a JOIN one b ON a.e = b.e AND a.r2 < b.r)", "allc AS (SELECT r AS rels, count(*) AS n_ent FROM one GROUP BY 1 UNION ALL SELECT r1 || ',' || r2, count(*) FROM two GROUP BY 1 UNION ALL SELECT r1 || ',' || r2 || ',' || r3, count(*) FROM three GROUP BY 1)", select="SELECT rels, n_ent FROM allc WHERE n_ent >= 20"))
def combo_cover(spark, d):
    """Frequent combinations of up to three relations with their covers."""
    p = cats.profiles_of(cats.entity_profiles(cats.entity_relations(fx.trade(spark, d))))
    return cats.frequent_combos(p, 20).select(F.array_join("rels", ",").alias("rels"), F.col("n_ent").cast("long").alias("n_ent"))


@query(over("trade", _SETS, "one AS (SELECT r, count(*) AS n FROM pairs GROUP BY r)", "mix AS (SELECT a.r AS r1, b.r AS r2, count(*) AS n FROM pairs a JOIN pairs b ON a.e = b.e AND a.r < b.r GROUP BY ALL)", select="SELECT r1, r2, round(mix.n / (x.n + y.n - mix.n), 6) AS jaccard FROM mix JOIN one x ON r1 = x.r JOIN one y ON r2 = y.r"))
def overlap_jaccard(spark, d):
    """Overlap of relations' entity sets, the measure of merging, over profiles."""
    p = cats.profiles_of(cats.entity_profiles(cats.entity_relations(fx.trade(spark, d)))).select("profile", "n_ent", F.explode("rels").alias("r"))
    n = p.groupBy("r").agg(F.sum("n_ent").alias("n"))
    both = p.select("profile", "n_ent", F.col("r").alias("r1")).join(p.select("profile", F.col("r").alias("r2")), "profile").where("r1 < r2").groupBy("r1", "r2").agg(F.sum("n_ent").alias("b"))
    out = both.join(n.select(F.col("r").alias("r1"), F.col("n").alias("x")), "r1").join(n.select(F.col("r").alias("r2"), F.col("n").alias("y")), "r2")
    return out.select("r1", "r2", r6(F.col("b") / (F.col("x") + F.col("y") - F.col("b"))).alias("jaccard"))


@query(over("trade", _SETS, select="SELECT r, count(*) AS n FROM (SELECT e, unnest(rels) AS r FROM sets) GROUP BY r"))
def explode_categories(spark, d):
    sets = cats.entity_profiles(cats.entity_relations(fx.trade(spark, d)))
    return sets.select(F.explode("rels").alias("r")).groupBy("r").agg(F.count(F.lit(1)).alias("n"))


@query("SELECT p_partkey, round(" + choose("p_partkey + 60", "p_size") + ", 4) AS bits FROM part")
def udf_choose_exact(spark, d):
    """The same logarithms by exact integers, in an Arrow-batched function."""
    from ..functions.mdl import log2_choose_exact

    @F.pandas_udf("double")
    def exact(n: pd.Series, k: pd.Series) -> pd.Series:
        return pd.Series([log2_choose_exact(int(a), int(b)) for a, b in zip(n, k, strict=True)])

    return fx.table(spark, d, "part").select("p_partkey", F.round(exact(F.col("p_partkey") + 60, F.col("p_size")), 4).alias("bits"))


@query(over("clicks", "c AS (SELECT r, s, count(*) AS n FROM facts GROUP BY ALL)", select="SELECT r, round(sum(n) * log2(sum(n)) - sum(n * log2(n)), 4) AS bits FROM c GROUP BY r"))
def uda_entropy(spark, d):
    """Code lengths of subjects by a grouped Arrow aggregate over counts (the built-in form is ``entropy_bits``)."""
    import numpy as np

    @F.pandas_udf("double")
    def entropy(n: pd.Series) -> float:
        x = n.to_numpy(dtype=float)
        return float(x.sum() * np.log2(x.sum()) - (x * np.log2(x)).sum())

    return fx.clicks(spark, d).groupBy("r", "s").agg(F.count(F.lit(1)).alias("n")).groupBy("r").agg(F.round(entropy("n"), 4).alias("bits"))


@query(over("validity", select="SELECT s, r, o, CAST(unnest(generate_series(CAST(t_start AS BIGINT), CAST(t_end AS BIGINT), 30)) AS BIGINT) AS t FROM facts"))
def udtf_walk(spark, d):
    """Ticks of a duration, 30 apart, by a table function."""

    @F.udtf(returnType="t: bigint")
    class Walk:
        def eval(self, start: int, end: int):
            for t in range(start, end + 1, 30):
                yield (t,)

    spark.udtf.register("walk_ticks", Walk)
    fx.validity(spark, d).createOrReplaceTempView("validity_facts")
    return spark.sql("SELECT s, r, o, w.t FROM validity_facts, LATERAL walk_ticks(t_start, t_end) w")


@query(over("dialogue", select="SELECT s, r, o, CAST(t AS BIGINT) AS t FROM facts"))
def json_round_trip(spark, d):
    """Facts through JSON lines and back."""
    from ..storage import new_path

    path = new_path(spark, "json")
    fx.dialogue(spark, d).write.json(path)
    return spark.read.schema("s string, r string, o string, t long").json(path)


@query(over("clicks", _CHAIN, select="SELECT s, o, count(*) AS n FROM chain GROUP BY ALL"))
def history_bucketed(spark, d):
    """History in buckets of the pair: sequences and joins within pairs need no shuffle."""
    import uuid

    from ..storage import new_path

    name = f"history_{uuid.uuid4().hex}"
    fx.clicks(spark, d).write.bucketBy(8, "s", "o").sortBy("s", "o", "t").option("path", new_path(spark, "buckets")).saveAsTable(name)
    return oc.chain_pairs(spark.table(name), 20).groupBy("s", "o").agg(F.count(F.lit(1)).alias("n"))


_WIT = """wit AS (SELECT DISTINCT f.s, f.o, f.r, f.t, h.r AS r_head FROM facts f JOIN facts h ON f.s = h.s AND f.o = h.o AND h.t < f.t AND f.t - h.t <= 30),
lk AS (SELECT DISTINCT substr(s, 1, 1) AS cs, substr(o, 1, 1) AS co, r_head, r FROM wit),
own AS (SELECT s, o, t, r_head, list(DISTINCT r) AS rs FROM wit GROUP BY ALL),
l0 AS (SELECT f.s, f.o, f.r, f.t, k.r_head, w.r_head IS NOT NULL AS ok FROM facts f JOIN lk k ON substr(f.s, 1, 1) = k.cs AND substr(f.o, 1, 1) = k.co AND f.r = k.r LEFT JOIN wit w ON f.s = w.s AND f.o = w.o AND f.r = w.r AND f.t = w.t AND k.r_head = w.r_head),
l1 AS (SELECT a.s, a.o, a.r, a.t, a.r_head AS r_mid, k.r_head, w.r_head IS NOT NULL AS ok FROM l0 a JOIN lk k ON substr(a.s, 1, 1) = k.cs AND substr(a.o, 1, 1) = k.co AND a.r_head = k.r LEFT JOIN wit w ON a.s = w.s AND a.o = w.o AND a.r = w.r AND a.t = w.t AND k.r_head = w.r_head WHERE NOT a.ok)"""


@query(over("lifecycle", _WIT, select="SELECT 0 AS hop, r, ok, count(*) AS n FROM l0 GROUP BY ALL UNION ALL SELECT 1, r_mid, ok, count(*) FROM l1 GROUP BY ALL"))
def walk_reach(spark, d):
    """The walk over all chain links, kinds as categories, one hop back: precursors found and not, by relation and hop."""
    from ..operators import scoring as sc
    from .experiments import all_links

    facts = fx.with_ids(fx.lifecycle_by_pair(spark, d))
    trace, _, _ = sc.walk(facts, None, all_links(facts, 30), sc.ScoreConfig(K=1, horizon=30, closures=False), kept=False)
    return trace.groupBy(F.col("hop").cast("int").alias("hop"), "r", (F.col("status") == "ok").alias("ok")).agg(F.sum("mult").alias("n"))