"""The paper's kinds of data set, told on the given tables."""

from __future__ import annotations

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from .sources.io import load
from .spec import Feature, JoinSpec, Relation

F_ = Feature


def relations(spark: SparkSession, sf: str, *names: str) -> dict[str, Relation]:
    keys = {"supplier": ("s_suppkey",), "part": ("p_partkey",), "orders": ("o_orderkey",), "customer": ("c_custkey",), "nation": ("n_nationkey",), "region": ("r_regionkey",)}
    return {n: Relation(n, load(spark, sf, n), keys.get(n, ()), n in keys) for n in names}


EDGES = {
    "supplier": ("lineitem", "supplier", (("l_suppkey", "s_suppkey"),)),
    "part": ("lineitem", "part", (("l_partkey", "p_partkey"),)),
    "orders": ("lineitem", "orders", (("l_orderkey", "o_orderkey"),)),
    "customer": ("orders", "customer", (("o_custkey", "c_custkey"),)),
    "nation": ("supplier", "nation", (("s_nationkey", "n_nationkey"),)),
    "region": ("nation", "region", (("n_regionkey", "r_regionkey"),)),
}


def star(spark: SparkSession, sf: str, *dims: str, where: dict | None = None) -> JoinSpec:
    return JoinSpec(relations(spark, sf, "lineitem", *dims), tuple(EDGES[d] for d in dims), where or {})


def period(spark: SparkSession, sf: str, part: str) -> dict[str, str]:
    """Condition for all but the last month (train) or that month (test); quarter: a fourth of the orders."""
    if part == "full":
        return {}
    if part == "quarter":
        return {"lineitem": "l_orderkey % 4 = 0"}
    last = load(spark, sf, "lineitem").selectExpr("cast(max(l_shipdate) - interval 1 month as string) as m").first().m
    return {"lineitem": f"l_shipdate {'<=' if part == 'train' else '>'} timestamp '{last}'"}


def running3(spark, sf) -> tuple[JoinSpec, list[Feature], Feature]:
    fs = [F_("i", "lineitem", "l_partkey"), F_("s", "lineitem", "l_suppkey"), F_("c", "supplier", "s_nationkey"), F_("p", "part", "p_retailprice", scale=2)]
    return star(spark, sf, "supplier", "part"), fs, F_("u", "lineitem", "l_quantity")


def narrow6(spark, sf, part: str = "full") -> tuple[JoinSpec, list[Feature], Feature]:
    fs = [F_(n, o, n, scale=2) for n, o in (("l_extendedprice", "lineitem"), ("l_discount", "lineitem"), ("l_tax", "lineitem"), ("o_totalprice", "orders"), ("p_retailprice", "part"), ("s_acctbal", "supplier"))]
    return star(spark, sf, "orders", "part", "supplier", "nation", where=period(spark, sf, part)), fs, F_("l_quantity", "lineitem", "l_quantity")


#: (name, owner, SQL that Spark and the oracle read alike; dow() is made equal by each side)
WIDE = [
    ("l_extendedprice", "lineitem", "l_extendedprice"), ("l_discount", "lineitem", "l_discount"), ("l_tax", "lineitem", "l_tax"), ("l_linenumber", "lineitem", "l_linenumber"),
    ("ship_year", "lineitem", "year(l_shipdate)"), ("ship_month", "lineitem", "month(l_shipdate)"), ("ship_day", "lineitem", "day(l_shipdate)"), ("ship_dow", "lineitem", "dow(l_shipdate)"),
    ("net_price", "lineitem", "l_extendedprice * (1 - l_discount)"), ("price_tax", "lineitem", "l_extendedprice * l_tax"), ("discount_sq", "lineitem", "l_discount * l_discount"),
    ("o_totalprice", "orders", "o_totalprice"), ("order_year", "orders", "year(o_orderdate)"), ("order_month", "orders", "month(o_orderdate)"), ("order_day", "orders", "day(o_orderdate)"), ("order_dow", "orders", "dow(o_orderdate)"),
    ("priority", "orders", "cast(substring(o_orderpriority, 1, 1) as int)"), ("total_sq", "orders", "o_totalprice * o_totalprice"), ("finished", "orders", "case when o_orderstatus = 'F' then 1 else 0 end"),
    ("c_acctbal", "customer", "c_acctbal"), ("c_nationkey", "customer", "c_nationkey"), ("c_debt", "customer", "case when c_acctbal < 0 then 1 else 0 end"), ("c_bal_sq", "customer", "c_acctbal * c_acctbal"), ("segment_len", "customer", "length(c_mktsegment)"),
    ("p_size", "part", "p_size"), ("p_retailprice", "part", "p_retailprice"), ("p_size_sq", "part", "p_size * p_size"), ("brand_no", "part", "cast(regexp_extract(p_brand, '([0-9]+)', 1) as int)"), ("p_name_len", "part", "length(p_name)"), ("p_price_sq", "part", "p_retailprice * p_retailprice"),
    ("s_acctbal", "supplier", "s_acctbal"), ("s_nationkey", "supplier", "s_nationkey"), ("s_debt", "supplier", "case when s_acctbal < 0 then 1 else 0 end"), ("s_bal_sq", "supplier", "s_acctbal * s_acctbal"), ("s_nation_sq", "supplier", "s_nationkey * s_nationkey"),
]


def wide35(spark, sf, part: str = "full") -> tuple[JoinSpec, list[Feature], Feature]:
    fs = [F_(n, o, e.replace("dow(", "-1 + dayofweek(")) for n, o, e in WIDE]
    return star(spark, sf, "orders", "customer", "part", "supplier", where=period(spark, sf, part)), fs, F_("l_quantity", "lineitem", "l_quantity")


CATEGORIES = [("p_type", "part"), ("c_mktsegment", "customer"), ("o_orderpriority", "orders"), ("l_returnflag", "lineitem"), ("n_regionkey", "nation"), ("p_brand", "part")]


def onehot(spark, sf) -> tuple[JoinSpec, list[Feature], list[Feature]]:
    spec = star(spark, sf, "orders", "customer", "part", "supplier", "nation", "region")
    cont = narrow6(spark, sf)[1]
    return spec, cont, [F_(n, o, f"cast({n} as string)", "cat") for n, o in CATEGORIES]


def planted_linear(spark, sf) -> tuple[JoinSpec, list[Feature], Feature]:
    """Label 3 + 2 quantity + 0.5 size - 0.01 (price - 950) of joined columns: carried by a relation of joined rows."""
    df = _joined_parts(spark, sf).selectExpr("l_partkey", "l_quantity", "3 + 2 * l_quantity + 0.5 * p_size - 0.01 * (p_retailprice - 950) as y")
    rel = {"lineitem": Relation("lineitem", df), **relations(spark, sf, "part")}
    fs = [F_("l_quantity", "lineitem", "l_quantity"), F_("p_size", "part", "p_size"), F_("p_retailprice", "part", "p_retailprice")]
    return JoinSpec(rel, (EDGES["part"],)), fs, F_("y", "lineitem", "y")


def _joined_parts(spark, sf) -> DataFrame:
    line, part = load(spark, sf, "lineitem"), load(spark, sf, "part")
    return line.join(part, line.l_partkey == part.p_partkey)


def planted_tree(spark, sf) -> tuple[JoinSpec, list[Feature], Feature]:
    """Label 10 [p_size <= 25] + 5 [o_totalprice <= 250000]."""
    orders = load(spark, sf, "orders")
    df = _joined_parts(spark, sf).join(orders, F.col("l_orderkey") == orders.o_orderkey)
    df = df.selectExpr("l_partkey", "l_orderkey", "l_suppkey", "(case when p_size <= 25 then 10 else 0 end) + (case when o_totalprice <= 250000 then 5 else 0 end) as y")
    rel = {"lineitem": Relation("lineitem", df), **relations(spark, sf, "part", "orders", "supplier")}
    fs = [F_("p_size", "part", "p_size"), F_("o_totalprice", "orders", "o_totalprice"), F_("p_retailprice", "part", "p_retailprice"), F_("s_acctbal", "supplier", "s_acctbal")]
    return JoinSpec(rel, (EDGES["part"], EDGES["orders"], EDGES["supplier"])), fs, F_("y", "lineitem", "y")


def events_star(spark, sf) -> tuple[JoinSpec, list[Feature], Feature]:
    rel = relations(spark, sf, "events", "customer", "nation")
    edges = (("events", "customer", (("user_id", "c_custkey"),)), ("customer", "nation", (("c_nationkey", "n_nationkey"),)))
    fs = [F_("c_acctbal", "customer", "c_acctbal"), F_("k", "events", "coalesce(cast(get_json_object(props, '$.k') as int), 0)")]
    return JoinSpec(rel, edges), fs, F_("value", "events", "value")
