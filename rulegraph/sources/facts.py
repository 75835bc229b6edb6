"""Fact tables (s, r, o, t) and (s, r, o, t_start, t_end) over the given tables.

Facts are sets: rows equal in all columns count once. Entity names carry their kind as
first letter; ticks are days from 1995-01-01 or hours from 2024-01-01.
"""

from __future__ import annotations

from collections.abc import Callable

from pyspark.sql import Column, DataFrame, SparkSession
from pyspark.sql import functions as F

from ..storage import buckets, staged_by

DAY_ZERO = "1995-01-01"
HOUR_ZERO = "2024-01-01 00:00:00"


def table(spark: SparkSession, sf_dir: str, name: str) -> DataFrame:
    return spark.read.parquet(f"{sf_dir}/{name}.parquet")


def named(kind: str, key: str | Column) -> Column:
    return F.concat(F.lit(kind), F.col(key).cast("string") if isinstance(key, str) else key)


def day(ts: str) -> Column:
    return F.date_diff(F.to_date(ts), F.to_date(F.lit(DAY_ZERO))).cast("long")


def hour(ts: str) -> Column:
    return F.floor((F.unix_seconds(F.col(ts).cast("timestamp")) - F.unix_seconds(F.to_timestamp(F.lit(HOUR_ZERO)))) / 3600).cast("long")


def month(ts: str) -> Column:
    return ((F.year(ts) - 1995) * 12 + F.month(ts) - 1).cast("long")


def _sales(spark: SparkSession, sf_dir: str) -> DataFrame:
    lines = table(spark, sf_dir, "lineitem").select("l_orderkey", "l_partkey", "l_suppkey", "l_linenumber", "l_returnflag", "l_linestatus", "l_shipdate")
    orders = table(spark, sf_dir, "orders").select(F.col("o_orderkey").alias("l_orderkey"), "o_custkey", "o_orderdate")
    return lines.join(orders, "l_orderkey").select(
        "l_orderkey", "l_linenumber", named("C", "o_custkey").alias("c"), named("S", "l_suppkey").alias("u"), named("P", "l_partkey").alias("p"), "l_partkey",
        F.concat(F.lit("trade_"), "l_returnflag", "l_linestatus").alias("deal"), day("o_orderdate").alias("ordered"), day("l_shipdate").alias("shipped"),
    )


def _facts(df: DataFrame, s, r, o, t) -> DataFrame:
    one = lambda x: x if isinstance(x, Column) else F.col(x)
    return df.select(one(s).alias("s"), one(r).alias("r"), one(o).alias("o"), one(t).cast("long").alias("t"))


def trade(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Orders, shipments and deals among customers, suppliers, parts and nations, by day."""
    sales = _sales(spark, sf_dir)
    typed = sales.join(table(spark, sf_dir, "part").select(F.col("p_partkey").alias("l_partkey"), "p_type"), "l_partkey")
    first_order = sales.groupBy("c").agg(F.min("ordered").alias("t"))
    first_ship = sales.groupBy("u").agg(F.min("shipped").alias("t"))
    customers = table(spark, sf_dir, "customer").select(named("C", "c_custkey").alias("c"), named("N", "c_nationkey").alias("n")).join(first_order, "c", "left")
    suppliers = table(spark, sf_dir, "supplier").select(named("S", "s_suppkey").alias("u"), named("N", "s_nationkey").alias("n")).join(first_ship, "u", "left")
    zero = F.coalesce(F.col("t"), F.lit(0))
    parts = [
        _facts(typed, "c", F.concat(F.lit("orders_"), "p_type"), "p", "ordered"),
        _facts(typed, "u", F.concat(F.lit("ships_"), "p_type"), "p", "shipped"),
        _facts(sales, "c", "deal", "u", "shipped"),
        _facts(customers, "c", F.lit("based_in"), "n", zero),
        _facts(suppliers, "u", F.lit("registered_in"), "n", zero),
    ]
    return _union(parts)


def clicks(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Users acting on keys, the action's kind split by value, by hour."""
    return click_facts(table(spark, sf_dir, "events")).distinct()


def click_facts(events: DataFrame) -> DataFrame:
    """The same row by row (batch or stream), with event_id and ts kept out."""
    step = F.when(F.col("value") < 15, 0).when(F.col("value") < 35, 1).when(F.col("value") < 70, 2).otherwise(3)
    return _facts(events, named("U", "user_id"), F.concat_ws("_", "event_type", step.cast("string")), named("K", F.get_json_object("props", "$.k")), hour("ts"))


def lifecycle(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Want, stock, request, confirm, receive: a planted order of events; one chain in 20 lacks its confirmation."""
    return lifecycle_rows(spark, sf_dir).distinct()


def lifecycle_rows(spark: SparkSession, sf_dir: str) -> DataFrame:
    """The facts of :func:`lifecycle`, some of them more than once: lines meet orders once and give all their facts together."""
    d = F.col("ordered")
    confirmed = (7 * F.col("l_orderkey") + F.col("l_linenumber")) % 20 != 0
    fact = lambda s, r, o, t: F.struct(F.col(s).alias("s"), F.lit(r).alias("r"), F.col(o).alias("o"), t.cast("long").alias("t"))
    facts = F.array(
        fact("c", "want", "p", d),
        fact("u", "stock", "p", d),
        fact("c", "request", "u", d + 1),
        fact("c", "receive", "u", d + 10 + F.col("l_linenumber") % 5),
        F.when(confirmed, fact("c", "confirm", "u", d + 2 + F.col("l_orderkey") % 3)),
    )
    return _sales(spark, sf_dir).select(F.explode(facts).alias("f")).where("f is not null").select("f.s", "f.r", "f.o", "f.t")


#: Facts of so many lines are shuffled at once where they are kept by pair: one part's shuffle is gone before the next one's.
LINES_AT_ONCE = 10_000_000


def lifecycle_by_pair(spark: SparkSession, sf_dir: str) -> DataFrame:
    """The facts of :func:`lifecycle`, kept in buckets of their pairs by one shuffle, which moves the facts that a line gives a pair together.

    Pairs are dealt to parts by hash, and parts are made one after the other, so disk holds one part's shuffle.
    """
    names = ["want", "stock", "request", "receive", "confirm"]
    d = F.col("ordered")
    confirmed = (7 * F.col("l_orderkey") + F.col("l_linenumber")) % 20 != 0
    fact = lambda r, t: F.shiftleft(t.cast("long"), 3).bitwiseOR(F.lit(names.index(r)))
    pair = lambda s, o, *facts: F.struct(F.col(s).alias("s"), F.col(o).alias("o"), F.array(*facts).alias("facts"))
    pairs = F.array(
        pair("c", "p", fact("want", d)),
        pair("u", "p", fact("stock", d)),
        pair("c", "u", fact("request", d + 1), fact("receive", d + 10 + F.col("l_linenumber") % 5), F.when(confirmed, fact("confirm", d + 2 + F.col("l_orderkey") % 3))),
    )
    rows = _sales(spark, sf_dir).select(F.explode(pairs).alias("f")).select("f.*")
    n = 1 + table(spark, sf_dir, "lineitem").count() // LINES_AT_ONCE
    parts = [rows.where(F.pmod(F.xxhash64("s", "o"), F.lit(n)) == i) for i in range(n)] if n > 1 else [rows]
    relation = F.element_at(F.array(*[F.lit(x) for x in names]), (F.col("f").bitwiseAND(F.lit(7)) + 1).cast("int"))
    told = lambda part: part.repartition(buckets(spark), "s", "o").select("s", "o", F.explode("facts").alias("f")).where("f is not null").select("s", relation.alias("r"), "o", F.shiftright("f", 3).alias("t")).distinct()
    return staged_by([told(part) for part in parts], "lifecycle", ["s", "o"])


def dialogue(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Conversations saying things of some length to roles, by turn."""
    size = F.length(F.coalesce("text", F.lit("")))
    bucket = F.when(size < 100, "short").when(size < 500, "medium").otherwise("long")
    return _facts(table(spark, sf_dir, "conversations"), named("V", "conv_id"), F.concat(F.lit("says_"), bucket), named("R", "role"), "turn").distinct()


def links(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Hosts linking to paths, read out of pages' addresses and text."""
    pages = table(spark, sf_dir, "pages").select("page_id", F.regexp_extract("url", r"^([a-z]+)://([^/]+)", 2).alias("host"), F.explode(F.regexp_extract_all("html", F.lit(r'href="([^"]*)"'), 1)).alias("href"))
    scheme = F.when(F.col("href").rlike("^https?://"), F.regexp_extract("href", "^([a-z]+):", 1)).otherwise("local")
    path = F.regexp_extract("href", r"^(?:[a-z]+://[^/]+)?(.*)$", 1)
    section = F.regexp_extract(path, r"^/?([A-Za-z]*)", 1)
    return _facts(pages, named("H", F.col("host")), F.concat_ws("_", F.lit("links"), scheme, section), named("A", path), "page_id").distinct()


def mentions(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Sources publishing in languages, with labels where a document has some, by document."""
    labels = table(spark, sf_dir, "labels").select("doc_id", "quality", "toxic")
    joined = table(spark, sf_dir, "documents").select("doc_id", "source", "lang").join(labels, "doc_id", "left")
    relation = F.when(F.col("quality").isNull(), F.lit("publishes_unlabelled")).otherwise(F.concat(F.lit("publishes_q"), F.col("quality").cast("string"), F.lit("_t"), F.col("toxic").cast("string")))
    return _facts(joined, named("D", "source"), relation, named("G", "lang"), "doc_id").distinct()


def near(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Vectors belonging to classes."""
    return _facts(table(spark, sf_dir, "embeddings"), named("X", "vec_id"), F.lit("is_class"), named("Y", "label"), F.lit(0)).distinct()


def validity(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Deals with a duration: from the order to the shipment."""
    sales = _sales(spark, sf_dir).where("ordered <= shipped")
    return sales.select(F.col("c").alias("s"), F.col("deal").alias("r"), F.col("u").alias("o"), F.col("ordered").alias("t_start"), F.col("shipped").alias("t_end")).distinct()


def _rows(parts: list[DataFrame]) -> DataFrame:
    out = parts[0]
    for part in parts[1:]:
        out = out.unionByName(part)
    return out


def _union(parts: list[DataFrame]) -> DataFrame:
    return _rows(parts).distinct()


FIXTURES: dict[str, Callable[[SparkSession, str], DataFrame]] = {"trade": trade, "clicks": clicks, "lifecycle": lifecycle, "dialogue": dialogue, "links": links, "mentions": mentions, "near": near}

#: The same facts, not made a set where that takes a shuffle of its own.
ROWS = FIXTURES | {"lifecycle": lifecycle_rows}


def with_ids(facts: DataFrame) -> DataFrame:
    """fact_id is a content hash, so it does not depend on partitioning or order."""
    return facts.select(F.xxhash64("s", "r", "o", "t").alias("fact_id"), "s", "r", "o", "t")


def encode(facts: DataFrame) -> DataFrame:
    """Entities and relations as 64-bit content hashes: shuffles move eight bytes a key."""
    return facts.select(F.xxhash64("s").alias("s"), F.xxhash64("r").alias("r"), F.xxhash64("o").alias("o"), "t")


def dictionary(facts: DataFrame) -> DataFrame:
    """Names behind the hashes of :func:`encode`: id, name, is_relation."""
    one = lambda c, rel: facts.select(F.xxhash64(c).alias("id"), F.col(c).cast("string").alias("name"), F.lit(rel).alias("is_relation"))
    return one("s", False).unionByName(one("o", False)).unionByName(one("r", True)).distinct()


def read_triples(spark: SparkSession, path: str, sep: str = "\t") -> DataFrame:
    """Facts from a text file of s, r, o, t columns."""
    return spark.read.csv(path, sep=sep, schema="s string, r string, o string, t long").where("s is not null and r is not null and o is not null and t is not null").distinct()


def write_history(facts: DataFrame, path: str, ticks: int = 30) -> None:
    """Facts as Parquet partitioned by a coarse time bucket, so time filters prune folders."""
    facts.withColumn("t_bucket", F.floor(F.col("t") / ticks)).repartition("t_bucket").write.mode("overwrite").partitionBy("t_bucket").parquet(path)
