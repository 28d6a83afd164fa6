"""Views of the given tables as private tuples, with the DuckDB text of the same view."""

from __future__ import annotations

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from ldpspark.plans.schema import Categorical, Numeric, TupleSpec, normalised
from ldpspark.sources.tables import load

LINE_KEY = ("l_orderkey", "l_linenumber", "l_partkey", "l_suppkey", "cast(round(l_extendedprice * 100) as bigint)")

#: Public bounds and domains (fixed values of the collection).
QUANTITY = Numeric("quantity", "l_quantity", 1.0, 50.0)
PRICE = Numeric("price", "l_extendedprice", 0.0, 106000.0)
DISCOUNT = Numeric("discount", "l_discount", 0.0, 0.1)
TAX = Numeric("tax", "l_tax", 0.0, 0.08)
NET = Numeric("net_price", "l_extendedprice * (1 - l_discount) * (1 + l_tax)", 0.0, 120000.0)
BALANCE = Numeric("balance", "c_acctbal", -1000.0, 10000.0)
FLAG = Categorical("return_flag", "l_returnflag", 3, ("A", "N", "R"))
STATUS = Categorical("line_status", "l_linestatus", 2, ("F", "O"))
LINE_NO = Categorical("line_no", "l_linenumber - 1", 7)
ORDER_STATUS = Categorical("order_status", "o_orderstatus", 3, ("F", "O", "P"))
PRIORITY = Categorical("priority", "o_orderpriority", 5, ("1-URGENT", "2-HIGH", "3-MEDIUM", "4-NOT SPECIFIED", "5-LOW"))
SEGMENT = Categorical("segment", "c_mktsegment", 5, ("AUTOMOBILE", "BUILDING", "FURNITURE", "HOUSEHOLD", "MACHINERY"))
PART_TYPE = Categorical("part_type", "p_type", 6, ("ECONOMY", "LARGE", "MEDIUM", "PROMO", "SMALL", "STANDARD"))
ORDER_MONTH = Categorical("order_month", "month(o_orderdate) - 1", 12)
SHIP_WEEKDAY = Categorical("ship_weekday", "ship_dow", 7)
NEGATIVE = Categorical("negative_balance", "case when c_acctbal < 0 then 1 else 0 end", 2)

NUM4 = TupleSpec("num4", (QUANTITY, PRICE, DISCOUNT, TAX), (), LINE_KEY)
NUM6 = TupleSpec("num6", (NET, QUANTITY, PRICE, DISCOUNT, TAX, BALANCE), (), LINE_KEY)
CAT3 = TupleSpec("cat3", (), (FLAG, STATUS, LINE_NO), LINE_KEY)
LI23 = TupleSpec(
    "li23",
    (NET, QUANTITY, PRICE, DISCOUNT, TAX, BALANCE),
    (
        FLAG, STATUS, LINE_NO, ORDER_STATUS, PRIORITY, SEGMENT, PART_TYPE,
        Categorical("customer_region", "cn_regionkey", 5), Categorical("supplier_region", "sn_regionkey", 5),
        Categorical("ship_month", "month(l_shipdate) - 1", 12), ORDER_MONTH, SHIP_WEEKDAY,
        Categorical("size_band", "floor((p_size - 1) * 12 / 50)", 12),
        Categorical("order_weekend", "case when order_dow in (0, 6) then 1 else 0 end", 2),
        Categorical("late_ship", "late", 2), NEGATIVE, Categorical("order_weekday", "order_dow", 7),
    ),
    LINE_KEY,
)
LI18 = TupleSpec(
    "li18",
    LI23.numerics,
    (Categorical("brand", "brand_code", 25), Categorical("customer_nation", "c_nationkey", 25), ORDER_MONTH, SHIP_WEEKDAY, LINE_NO, PRIORITY, SEGMENT, PART_TYPE, ORDER_STATUS, FLAG, STATUS, NEGATIVE),
    LINE_KEY,
)


def wide(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Line items with the attributes of their order, customer, part and supplier.

    Nations are a fixed 25 rows and broadcast. The other sides grow with the data, so their joins are left to the planner,
    which broadcasts them only while they are small.
    """
    line = load(spark, sf_dir, "lineitem")
    nation = F.broadcast(load(spark, sf_dir, "nation").select("n_nationkey", "n_regionkey"))
    customer = load(spark, sf_dir, "customer").select("c_custkey", "c_nationkey", "c_acctbal", "c_mktsegment")
    customer = customer.join(nation, F.col("c_nationkey") == F.col("n_nationkey")).select("c_custkey", "c_nationkey", "c_acctbal", "c_mktsegment", F.col("n_regionkey").alias("cn_regionkey"))
    supplier = load(spark, sf_dir, "supplier").join(nation, F.col("s_nationkey") == F.col("n_nationkey")).select("s_suppkey", F.col("n_regionkey").alias("sn_regionkey"))
    orders = load(spark, sf_dir, "orders").select("o_orderkey", "o_custkey", "o_orderstatus", "o_orderdate", "o_orderpriority")
    part = load(spark, sf_dir, "part").select("p_partkey", "p_brand", "p_type", "p_size")
    out = line.join(orders, line["l_orderkey"] == orders["o_orderkey"]).join(customer, F.col("o_custkey") == F.col("c_custkey"))
    out = out.join(part, F.col("l_partkey") == F.col("p_partkey")).join(supplier, F.col("l_suppkey") == F.col("s_suppkey"))
    return out.withColumns({
        "ship_dow": F.dayofweek("l_shipdate") - 1,
        "order_dow": F.dayofweek("o_orderdate") - 1,
        "late": (F.col("l_shipdate") > F.col("o_orderdate") + F.expr("interval 60 days")).cast("int"),
        "brand_code": F.substring_index("p_brand", "#", -1).cast("int") - 1,
    })


WIDE_SQL = """
(SELECT l.*, o.o_orderstatus, o.o_orderdate, o.o_orderpriority, c.c_nationkey, c.c_acctbal, c.c_mktsegment, p.p_brand, p.p_type, p.p_size,
        cn.n_regionkey AS cn_regionkey, sn.n_regionkey AS sn_regionkey, dayofweek(l.l_shipdate) AS ship_dow, dayofweek(o.o_orderdate) AS order_dow,
        (l.l_shipdate > o.o_orderdate + INTERVAL 60 DAY)::INT AS late, split_part(p.p_brand, '#', 2)::INT - 1 AS brand_code
 FROM lineitem l JOIN orders o ON l.l_orderkey = o.o_orderkey JOIN customer c ON o.o_custkey = c.c_custkey JOIN part p ON l.l_partkey = p.p_partkey
 JOIN supplier s ON l.l_suppkey = s.s_suppkey JOIN nation cn ON c.c_nationkey = cn.n_nationkey JOIN nation sn ON s.s_nationkey = sn.n_nationkey)"""


def users(spark: SparkSession, sf_dir: str, spec: TupleSpec) -> DataFrame:
    """The tuples of a specification, normalised and coded."""
    plain = {a.name for a in (*NUM4.numerics, NET, *CAT3.categoricals)}
    narrow = all(a.name in plain for a in (*spec.numerics, *spec.categoricals))
    return normalised(load(spark, sf_dir, "lineitem") if narrow else wide(spark, sf_dir), spec)


def users_sql(spec: TupleSpec) -> str:
    """The same view as DuckDB text: (ukey, attributes...)."""
    plain = {a.name for a in (*NUM4.numerics, NET, *CAT3.categoricals)}
    narrow = all(a.name in plain for a in (*spec.numerics, *spec.categoricals))
    key = ", ".join(f"cast({k} as varchar)" for k in spec.key)
    columns = [f"concat_ws('|', {key}) AS ukey"]
    columns += [f"{a.sql()} AS {a.name}" for a in spec.numerics]
    columns += [f"{c.sql().replace('floor((p_size - 1) * 12 / 50)', '((p_size - 1) * 12 // 50)')} AS {c.name}" for c in spec.categoricals]
    return f"(SELECT {', '.join(columns)} FROM {'lineitem' if narrow else WIDE_SQL})"
