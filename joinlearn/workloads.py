"""Experiment workloads over the given tables, as feature queries with their variable orders."""

from __future__ import annotations

from dataclasses import replace

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from .operators.dependencies import Dependency
from .plans.order import VariableOrder
from .plans.query import FeatureQuery
from .sources.tables import renamed, table

CONTINUOUS = ("l_extendedprice", "l_discount", "l_tax", "p_size", "p_retailprice", "o_totalprice", "c_acctbal", "s_acctbal")
CATEGORICAL = ("l_returnflag", "l_linestatus", "p_brand", "p_type", "p_name", "o_orderpriority", "o_orderstatus", "c_mktsegment")
#: Factors that make each column whole.
SCALES = {"l_quantity": 1, "l_extendedprice": 100, "l_discount": 100, "l_tax": 100, "p_size": 1, "p_retailprice": 100, "o_totalprice": 100, "c_acctbal": 100, "s_acctbal": 100, "value": 100}
PART = Dependency("partkey", ("p_brand", "p_type", "p_name"))
STAR_ORDER = "suppkey(s_acctbal(s_nationkey), orderkey(custkey(c_mktsegment(c_acctbal), o_orderpriority(o_orderstatus(o_totalprice))), partkey(p_brand(p_type(p_name(p_size(p_retailprice)))), l_returnflag(l_linestatus(l_discount(l_tax(l_extendedprice(l_quantity))))))))"


def star_relations(spark: SparkSession, sf_dir: str) -> dict[str, DataFrame]:
    t = lambda n: table(spark, sf_dir, n)
    return {
        "lineitem": renamed(t("lineitem"), orderkey="l_orderkey", partkey="l_partkey", suppkey="l_suppkey", l_quantity="l_quantity", l_extendedprice="l_extendedprice", l_discount="l_discount", l_tax="l_tax", l_returnflag="l_returnflag", l_linestatus="l_linestatus"),
        "part": renamed(t("part"), partkey="p_partkey", p_brand="p_brand", p_type="p_type", p_name="p_name", p_size="p_size", p_retailprice="p_retailprice"),
        "orders": renamed(t("orders"), orderkey="o_orderkey", custkey="o_custkey", o_orderpriority="o_orderpriority", o_orderstatus="o_orderstatus", o_totalprice="o_totalprice"),
        "customer": renamed(t("customer"), custkey="c_custkey", c_mktsegment="c_mktsegment", c_acctbal="c_acctbal"),
        "supplier": renamed(t("supplier"), suppkey="s_suppkey", s_acctbal="s_acctbal", s_nationkey="s_nationkey"),
    }


def star(spark: SparkSession, sf_dir: str, workload: str = "W2", exact: bool = False, continuous: tuple | None = None, categorical: tuple | None = None, extra: tuple = ()) -> tuple[FeatureQuery, VariableOrder]:
    """W1 (one order in five), W2 (all rows), W3 (and the supplier's nation), W4 (and the part key, no nation), W4F (W4 after
    the part key's dependency)."""
    cats = {"W1": CATEGORICAL, "W2": CATEGORICAL, "W3": (*CATEGORICAL, "s_nationkey"), "W4": (*CATEGORICAL, "partkey"), "W4F": tuple(c for c in (*CATEGORICAL, "partkey") if c not in PART.determined)}[workload]
    cats = categorical if categorical is not None else cats
    cont = continuous if continuous is not None else CONTINUOUS
    where = {"lineitem": F.col("orderkey") % 5 == 0, "orders": F.col("orderkey") % 5 == 0} if workload == "W1" else {}
    query = FeatureQuery(star_relations(spark, sf_dir), cont, cats, "l_quantity", where, scale=SCALES if exact else None, extra=extra)
    return query, star_order(query)


def star_order(query: FeatureQuery) -> VariableOrder:
    """The workload's order, without the variables that the query leaves out."""
    full = VariableOrder.parse(STAR_ORDER)
    return pruned(full, set(query.variables()))


def pruned(order: VariableOrder, keep: set[str]) -> VariableOrder:
    def show(v: str) -> list[str]:
        below = [x for c in order.children[v] for x in show(c)]
        if v not in keep:
            return below
        return [v + (f"({', '.join(below)})" if below else "")]

    return VariableOrder.parse(", ".join(x for r in order.roots for x in show(r)))


def many_to_many(spark: SparkSession, sf_dir: str, exact: bool = False) -> tuple[FeatureQuery, VariableOrder]:
    """W5: events and order lines of a customer are independent given the customer."""
    t = lambda n: table(spark, sf_dir, n)
    query = FeatureQuery(
        {
            "events": renamed(t("events"), custkey="user_id", event_type="event_type", value="value"),
            "orders": renamed(t("orders"), custkey="o_custkey", orderkey="o_orderkey", o_orderpriority="o_orderpriority", o_orderstatus="o_orderstatus", o_totalprice="o_totalprice"),
            "lineitem": renamed(t("lineitem"), orderkey="l_orderkey", l_extendedprice="l_extendedprice", l_discount="l_discount", l_quantity="l_quantity"),
        },
        ("value", "o_totalprice", "l_extendedprice", "l_discount"), ("event_type", "o_orderpriority", "o_orderstatus"), "l_quantity", scale=SCALES if exact else None,
    )
    return query, VariableOrder.parse("custkey(event_type(value), orderkey(o_orderpriority(o_orderstatus(o_totalprice)), l_discount(l_extendedprice(l_quantity))))")


def activity(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Derived relation: events by user and day of month."""
    e = table(spark, sf_dir, "events")
    flag = lambda k: F.max(F.when(F.col("event_type") == k, 1).otherwise(0)).alias(f"saw_{k}")
    return e.groupBy(F.col("user_id").alias("custkey"), F.dayofmonth("ts").alias("dom")).agg(F.count(F.lit(1)).alias("n_events"), F.sum(F.round(F.col("value") * 100).cast("long")).alias("cents"), flag("click"), flag("purchase"), flag("error"))


def census(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Derived relation: customers by nation."""
    c, n = table(spark, sf_dir, "customer"), table(spark, sf_dir, "nation")
    by = c.groupBy(F.col("c_nationkey").alias("n_nationkey")).agg(F.count(F.lit(1)).alias("n_customers"), F.sum(F.round(F.col("c_acctbal") * 100).cast("long")).alias("cents"))
    out = n.join(by, "n_nationkey", "left")
    return out.select(F.col("n_nationkey").alias("nationkey"), "n_regionkey", F.coalesce("n_customers", F.lit(0)).alias("n_customers"), F.coalesce("cents", F.lit(0)).alias("cents"))


def composite(spark: SparkSession, sf_dir: str, exact: bool = False) -> tuple[FeatureQuery, VariableOrder]:
    """W6: a dimension on the composite key (customer, day of month)."""
    o = table(spark, sf_dir, "orders").select(F.col("o_custkey").alias("custkey"), F.dayofmonth("o_orderdate").alias("dom"), "o_totalprice", "o_orderpriority")
    a = activity(spark, sf_dir).select("custkey", "dom", "n_events", "saw_click", "saw_purchase")
    query = FeatureQuery({"orders": o, "activity": a}, ("n_events",), ("saw_click", "saw_purchase", "o_orderpriority"), "o_totalprice", scale=SCALES if exact else None)
    return query, VariableOrder.parse("custkey(dom(n_events(saw_click(saw_purchase)), o_orderpriority(o_totalprice)))")


def nation_pairs(spark: SparkSession, sf_dir: str, exact: bool = False) -> tuple[FeatureQuery, VariableOrder]:
    """W12: customers and suppliers of a nation."""
    c = renamed(table(spark, sf_dir, "customer"), nationkey="c_nationkey", c_acctbal="c_acctbal", c_mktsegment="c_mktsegment")
    s = renamed(table(spark, sf_dir, "supplier"), nationkey="s_nationkey", s_acctbal="s_acctbal")
    query = FeatureQuery({"customer": c, "supplier": s}, ("c_acctbal",), ("c_mktsegment",), "s_acctbal", scale=SCALES if exact else None)
    return query, VariableOrder.parse("nationkey(c_mktsegment(c_acctbal), s_acctbal)")


def supplier_chain(spark: SparkSession, sf_dir: str, reduced: bool = False) -> tuple[FeatureQuery, VariableOrder, Dependency]:
    """W9: supplier determines nation, nation determines region."""
    li = renamed(table(spark, sf_dir, "lineitem"), suppkey="l_suppkey", l_quantity="l_quantity", l_discount="l_discount")
    su = renamed(table(spark, sf_dir, "supplier"), suppkey="s_suppkey", nationkey="s_nationkey")
    na = renamed(table(spark, sf_dir, "nation"), nationkey="n_nationkey", regionkey="n_regionkey")
    su = su.join(na, "nationkey")
    query = FeatureQuery({"lineitem": li, "supplier": su}, ("l_discount",), ("suppkey", "nationkey", "regionkey"), "l_quantity")
    order = VariableOrder.parse("suppkey(nationkey(regionkey), l_discount(l_quantity))")
    dep = Dependency("suppkey", ("nationkey", "regionkey"))
    if reduced:
        query = replace(query, categorical=("suppkey",))
        order = pruned(order, set(query.variables()))
    return query, order, dep


def toy(spark: SparkSession) -> tuple[FeatureQuery, VariableOrder]:
    """W7: the worked example's shape, values of our own."""
    r = spark.createDataFrame([(1, "b1", 2), (1, "b1", 3), (1, "b2", 5), (2, "b2", 7), (3, "b3", 9)], "A int, B string, C int")
    s = spark.createDataFrame([("b1", 10), ("b1", 20), ("b2", 30)], "B string, D int")
    t = spark.createDataFrame([(1, 4), (1, 6), (2, 4), (4, 6)], "A int, E int")
    return FeatureQuery({"R": r, "S": s, "T": t}, ("A", "C", "D"), ("B", "E")), VariableOrder.parse("A(B(C, D), E)")


def small_tree(spark: SparkSession, sf_dir: str, exact: bool = False) -> tuple[FeatureQuery, VariableOrder]:
    """The shape of W7 over given tables: customers with their nation, the nation's suppliers, the customer's orders."""
    r = renamed(table(spark, sf_dir, "customer"), A="c_custkey", B="c_nationkey", C="c_acctbal")
    s = renamed(table(spark, sf_dir, "supplier"), B="s_nationkey", D="s_acctbal")
    t = renamed(table(spark, sf_dir, "orders"), A="o_custkey", E="o_orderpriority")
    return FeatureQuery({"R": r, "S": s, "T": t}, ("A", "C", "D"), ("B", "E"), scale={"C": 100, "D": 100} if exact else None), VariableOrder.parse("A(B(C, D), E)")


def embedding_query(spark: SparkSession, sf_dir: str, width: int = 64) -> FeatureQuery:
    """W11: continuous-only vectors, the label as response."""
    e = table(spark, sf_dir, "embeddings")
    rows = e.select("vec_id", "label", *[F.col("embedding")[i].cast("double").alias(f"x{i}") for i in range(width)])
    return FeatureQuery({"embeddings": rows}, tuple(f"x{i}" for i in range(width)), (), "label")
