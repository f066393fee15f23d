"""Transaction views on the given tables: distinct (tid, item) pairs, in Spark and as DuckDB SQL."""

from __future__ import annotations

from dataclasses import dataclass

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from rulelattice.runtime import read_table


@dataclass(frozen=True)
class View:
    name: str
    build: object
    sql: str


def basket_part(spark: SparkSession, sf_dir: str) -> DataFrame:
    lines = read_table(spark, sf_dir, "lineitem")
    return lines.select(F.col("l_orderkey").alias("tid"), F.concat(F.lit("part"), F.col("l_partkey").cast("string")).alias("item"))


def _basket(column: str):
    def build(spark: SparkSession, sf_dir: str) -> DataFrame:
        lines, parts = read_table(spark, sf_dir, "lineitem"), read_table(spark, sf_dir, "part")
        return lines.join(parts, F.col("l_partkey") == F.col("p_partkey")).select(F.col("l_orderkey").alias("tid"), F.col(column).alias("item"))
    return build


def cust_profile(spark: SparkSession, sf_dir: str) -> DataFrame:
    lines, orders, parts = (read_table(spark, sf_dir, t) for t in ("lineitem", "orders", "part"))
    joined = lines.join(orders, F.col("l_orderkey") == F.col("o_orderkey")).join(parts, F.col("l_partkey") == F.col("p_partkey"))
    return joined.select(F.col("o_custkey").alias("tid"), F.concat_ws("/", "p_brand", "p_type").alias("item"))


def clicks(spark: SparkSession, sf_dir: str) -> DataFrame:
    events = read_table(spark, sf_dir, "events")
    bucket = F.floor(F.get_json_object("props", "$.k").cast("int") / 10).cast("string")
    return events.select((F.col("user_id") * 1000 + F.dayofyear("ts")).alias("tid"), F.concat_ws("_", "event_type", bucket).alias("item"))


def dense_order(spark: SparkSession, sf_dir: str) -> DataFrame:
    orders, customers, nations, regions = (read_table(spark, sf_dir, t) for t in ("orders", "customer", "nation", "region"))
    joined = (
        orders.join(customers, F.col("o_custkey") == F.col("c_custkey")).join(F.broadcast(nations), F.col("c_nationkey") == F.col("n_nationkey")).join(F.broadcast(regions), F.col("n_regionkey") == F.col("r_regionkey"))
    )  # nations and regions are tables of fixed size
    def attribute(name: str, value) -> object:
        return F.concat(F.lit(name + "="), value.cast("string"))
    def flag(name: str, test) -> object:
        return F.concat(F.lit(name + "="), F.when(test, "y").otherwise("n"))
    items = F.array(
        attribute("status", F.col("o_orderstatus")), attribute("prio", F.col("o_orderpriority")), attribute("seg", F.col("c_mktsegment")), attribute("region", F.col("r_name")),
        attribute("year", F.year("o_orderdate")), attribute("qtr", F.quarter("o_orderdate")), attribute("price", F.floor(F.col("o_totalprice") / 100000).cast("int")), attribute("bal", F.floor(F.col("c_acctbal") / 2500).cast("int")),
        attribute("dow", F.dayofweek("o_orderdate") - 1), flag("big", F.col("o_totalprice") > 250000), flag("neg", F.col("c_acctbal") < 0),
    )
    return joined.select(F.col("o_orderkey").alias("tid"), F.explode(items).alias("item"))


def doc_terms(spark: SparkSession, sf_dir: str) -> DataFrame:
    docs = read_table(spark, sf_dir, "documents")
    return docs.select(F.col("doc_id").alias("tid"), F.explode(F.array_distinct(F.regexp_extract_all(F.lower("text"), F.lit("([a-z]+)"), F.lit(1)))).alias("item"))


VIEWS = {
    v.name: v
    for v in (
        View("basket_part", basket_part, "select distinct l_orderkey as tid, 'part' || l_partkey as item from lineitem"),
        View("basket_name", _basket("p_name"), "select distinct l_orderkey as tid, p_name as item from lineitem join part on l_partkey = p_partkey"),
        View("basket_brand", _basket("p_brand"), "select distinct l_orderkey as tid, p_brand as item from lineitem join part on l_partkey = p_partkey"),
        View("cust_profile", cust_profile, "select distinct o_custkey as tid, p_brand || '/' || p_type as item from lineitem join orders on l_orderkey = o_orderkey join part on l_partkey = p_partkey"),
        View("clicks", clicks, "select distinct user_id * 1000 + dayofyear(ts) as tid, event_type || '_' || (json_extract_string(props, '$.k')::int // 10) as item from events"),
        View(
            "dense_order", dense_order,
            "select tid, unnest(items) as item from (select o_orderkey as tid, ['status=' || o_orderstatus, 'prio=' || o_orderpriority, 'seg=' || c_mktsegment, 'region=' || r_name, 'year=' || year(o_orderdate), 'qtr=' || quarter(o_orderdate), "
            "'price=' || floor(o_totalprice / 100000)::int, 'bal=' || floor(c_acctbal / 2500)::int, 'dow=' || dayofweek(o_orderdate), 'big=' || case when o_totalprice > 250000 then 'y' else 'n' end, 'neg=' || case when c_acctbal < 0 then 'y' else 'n' end] as items "
            "from orders join customer on o_custkey = c_custkey join nation on c_nationkey = n_nationkey join region on n_regionkey = r_regionkey)",
        ),
        View("doc_terms", doc_terms, "select distinct doc_id as tid, unnest(regexp_extract_all(lower(text), '[a-z]+')) as item from documents"),
    )
}


def pairs_of(spark: SparkSession, sf_dir: str, view: str) -> DataFrame:
    """(tid, item) of a view; pairs may repeat, the encoding makes them distinct."""
    return VIEWS[view].build(spark, sf_dir)
