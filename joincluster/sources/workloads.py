"""The experiment workloads over the given tables, as feature queries."""

from __future__ import annotations

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from ..plans.spec import Edge, Feature, FeatureQuery


def tables(spark: SparkSession, sf_dir: str, *names: str) -> list[DataFrame]:
    return [spark.read.parquet(f"{sf_dir}/{n}.parquet") for n in names]


def w_r(spark: SparkSession, sf_dir: str) -> FeatureQuery:
    """Retail: a fact table with keyed dimensions; the matrix has the fact table's rows."""
    li, o, c, n, r, p, s = tables(spark, sf_dir, "lineitem", "orders", "customer", "nation", "region", "part", "supplier")
    return FeatureQuery(
        "w_r", {"lineitem": li, "orders": o, "customer": c, "nation": n, "region": r, "part": p, "supplier": s},
        [Edge("lineitem", "orders", (("l_orderkey", "o_orderkey"),)), Edge("orders", "customer", (("o_custkey", "c_custkey"),)), Edge("customer", "nation", (("c_nationkey", "n_nationkey"),)),
         Edge("nation", "region", (("n_regionkey", "r_regionkey"),)), Edge("lineitem", "part", (("l_partkey", "p_partkey"),)), Edge("lineitem", "supplier", (("l_suppkey", "s_suppkey"),))],
        [Feature("qty", "lineitem", "l_quantity", "cont"), Feature("disc_cents", "lineitem", "cast(round(l_discount * 100) as bigint)", "cont"), Feature("size", "part", "p_size", "cont"),
         Feature("brand", "part", "p_brand"), Feature("type", "part", "p_type"), Feature("segment", "customer", "c_mktsegment"), Feature("nation", "nation", "n_name"), Feature("region", "region", "r_name")],
        "lineitem", [["nation", "region"]],
    ).validate()


def w_f(spark: SparkSession, sf_dir: str, lite: bool = False) -> FeatureQuery:
    """Grocery sales: a two-column key, a left join with a default, and derived dates."""
    li, o, p, s, n = tables(spark, sf_dir, "lineitem", "orders", "part", "supplier", "nation")
    sales = li.withColumn("day", F.to_date("l_shipdate"))
    tx = sales.groupBy("day", "l_suppkey").agg(F.count("*").alias("n"))
    oil = o.groupBy(F.to_date("o_orderdate").alias("day")).agg(F.floor(F.avg("o_totalprice")).alias("price"))
    days = sales.select("day").distinct().withColumn("weekend", F.dayofweek("day").isin(1, 7).cast("int"))
    feats = [
        Feature("units", "sales", "l_quantity", "cont"), Feature("promo", "sales", "cast(l_discount >= 0.07 as int)"), Feature("class", "part", "p_type"), Feature("price", "part", "p_retailprice", "cont"),
        Feature("nation", "nation", "n_name"), Feature("tx_n", "tx", "n", "cont"), Feature("oil", "oil", "price", "cont", default=0.0), Feature("no_oil", "oil", "0", default="1"), Feature("weekend", "days", "weekend"),
    ]
    q = FeatureQuery(
        "w_f", {"sales": sales, "part": p, "supplier": s, "nation": n, "tx": tx, "oil": oil, "days": days},
        [Edge("sales", "part", (("l_partkey", "p_partkey"),)), Edge("sales", "supplier", (("l_suppkey", "s_suppkey"),)), Edge("supplier", "nation", (("s_nationkey", "n_nationkey"),)),
         Edge("sales", "tx", (("day", "day"), ("l_suppkey", "l_suppkey"))), Edge("sales", "oil", (("day", "day"),), "left"), Edge("sales", "days", (("day", "day"),))],
        feats, "sales",
    ).validate()
    return q.only("units", "promo", "class", "weekend") if lite else q


def w_f_lite(spark: SparkSession, sf_dir: str) -> FeatureQuery:
    return w_f(spark, sf_dir, lite=True)


def w_y(spark: SparkSession, sf_dir: str) -> FeatureQuery:
    """Reviews: many categories per business, so the join outgrows its inputs."""
    e, c, o, n, r = tables(spark, sf_dir, "events", "customer", "orders", "nation", "region")
    cnt = o.groupBy("o_custkey").agg(F.count("*").alias("n_orders"))
    return FeatureQuery(
        "w_y", {"events": e, "customer": c, "orders": o, "cnt": cnt, "nation": n, "region": r},
        [Edge("events", "customer", (("user_id", "c_custkey"),)), Edge("customer", "orders", (("c_custkey", "o_custkey"),)), Edge("customer", "cnt", (("c_custkey", "o_custkey"),)),
         Edge("customer", "nation", (("c_nationkey", "n_nationkey"),)), Edge("nation", "region", (("n_regionkey", "r_regionkey"),))],
        [Feature("event_type", "events", "event_type"), Feature("segment", "customer", "c_mktsegment"), Feature("nation", "nation", "n_name"), Feature("region", "region", "r_name"),
         Feature("priority", "orders", "o_orderpriority"), Feature("status", "orders", "o_orderstatus"), Feature("n_orders", "cnt", "n_orders", "cont"), Feature("value", "events", "cast(round(value * 100) as bigint)", "cont")],
        "events", [["nation", "region"]],
    ).validate()


def w_m(spark: SparkSession, sf_dir: str) -> FeatureQuery:
    """Blow-up: customers' orders meet suppliers of the same nation."""
    o, c, s, n, r = tables(spark, sf_dir, "orders", "customer", "supplier", "nation", "region")
    return FeatureQuery(
        "w_m", {"orders": o, "customer": c, "nation": n, "supplier": s, "region": r},
        [Edge("orders", "customer", (("o_custkey", "c_custkey"),)), Edge("customer", "nation", (("c_nationkey", "n_nationkey"),)), Edge("nation", "supplier", (("n_nationkey", "s_nationkey"),)), Edge("nation", "region", (("n_regionkey", "r_regionkey"),))],
        [Feature("priority", "orders", "o_orderpriority"), Feature("status", "orders", "o_orderstatus"), Feature("segment", "customer", "c_mktsegment"), Feature("suppkey", "supplier", "s_suppkey"), Feature("nation", "nation", "n_name"), Feature("region", "region", "r_name")],
        "orders", [["nation", "region"]],
    ).validate()


def w_c(spark: SparkSession, sf_dir: str) -> FeatureQuery:
    """A cycle: supplier and customer of one order line are of the same nation."""
    c, o, li, s, n = tables(spark, sf_dir, "customer", "orders", "lineitem", "supplier", "nation")
    return FeatureQuery(
        "w_c", {"customer": c, "orders": o, "lineitem": li, "supplier": s, "nation": n},
        [Edge("customer", "orders", (("c_custkey", "o_custkey"),)), Edge("orders", "lineitem", (("o_orderkey", "l_orderkey"),)), Edge("lineitem", "supplier", (("l_suppkey", "s_suppkey"),)),
         Edge("supplier", "customer", (("s_nationkey", "c_nationkey"),)), Edge("customer", "nation", (("c_nationkey", "n_nationkey"),))],
        [Feature("segment", "customer", "c_mktsegment"), Feature("priority", "orders", "o_orderpriority"), Feature("nation", "nation", "n_name"), Feature("qty", "lineitem", "l_quantity", "cont")], "customer",
    ).validate()


def w_s(spark: SparkSession, sf_dir: str) -> FeatureQuery:
    """A many-to-many self-join."""
    (li,) = tables(spark, sf_dir, "lineitem")
    return FeatureQuery(
        "w_s", {"a": li, "b": li}, [Edge("a", "b", (("l_partkey", "l_partkey"),))],
        [Feature("qty_a", "a", "l_quantity", "cont"), Feature("flag_a", "a", "l_returnflag"), Feature("qty_b", "b", "l_quantity", "cont"), Feature("flag_b", "b", "l_returnflag")], "a",
    ).validate()


def w_d_geo(spark: SparkSession, sf_dir: str) -> FeatureQuery:
    """The geographic chain: customer, nation, region of every order."""
    o, c, n, r = tables(spark, sf_dir, "orders", "customer", "nation", "region")
    return FeatureQuery(
        "w_d_geo", {"orders": o, "customer": c, "nation": n, "region": r},
        [Edge("orders", "customer", (("o_custkey", "c_custkey"),)), Edge("customer", "nation", (("c_nationkey", "n_nationkey"),)), Edge("nation", "region", (("n_regionkey", "r_regionkey"),))],
        [Feature("custkey", "customer", "c_custkey"), Feature("nation", "nation", "n_name"), Feature("region", "region", "r_name")], "orders", [["custkey", "nation", "region"]],
    ).validate()


def w_d_calendar(spark: SparkSession, sf_dir: str) -> FeatureQuery:
    """The calendar chain of order dates; truncated dates, so that each level determines the next."""
    (o,) = tables(spark, sf_dir, "orders")
    cut = lambda unit: f"cast(date_trunc('{unit}', o_orderdate) as date)"
    return FeatureQuery(
        "w_d_calendar", {"orders": o}, [],
        [Feature("day", "orders", "to_date(o_orderdate)"), Feature("month", "orders", cut("month")), Feature("quarter", "orders", cut("quarter")), Feature("year", "orders", cut("year"))], "orders", [["day", "month", "quarter", "year"]],
    ).validate()


def w_t(spark: SparkSession, sf_dir: str) -> FeatureQuery:
    """Mixed types on other tables."""
    d, lab = tables(spark, sf_dir, "documents", "labels")
    return FeatureQuery(
        "w_t", {"documents": d, "labels": lab}, [Edge("documents", "labels", (("doc_id", "doc_id"),))],
        [Feature("n_chars", "documents", "n_chars", "cont"), Feature("lang", "documents", "lang"), Feature("source", "documents", "source"), Feature("quality", "labels", "quality"), Feature("toxic", "labels", "toxic")], "documents",
    ).validate()


def w_i(spark: SparkSession, sf_dir: str, first: str = "1998-05-13", last: str = "1998-05-20") -> tuple[DataFrame, DataFrame, DataFrame]:
    """Every product in every store with a week's sales, zero included: products (l, ...), stores (r, ...), observed (l, r, value)."""
    p, s, li = tables(spark, sf_dir, "part", "supplier", "lineitem")
    day = F.to_date("l_shipdate")
    seen = li.where(day.between(F.lit(first).cast("date"), F.lit(last).cast("date"))).groupBy(F.col("l_partkey").alias("l"), F.col("l_suppkey").alias("r")).agg(F.sum("l_quantity").alias("value"))
    return p.select(F.col("p_partkey").alias("l"), F.col("p_type").alias("type"), F.col("p_retailprice").alias("retailprice")), s.select(F.col("s_suppkey").alias("r"), F.col("s_acctbal").alias("acctbal")), seen


def w_v(spark: SparkSession, sf_dir: str) -> DataFrame:
    (e,) = tables(spark, sf_dir, "embeddings")
    return e


ALL = {f.__name__: f for f in (w_r, w_f, w_f_lite, w_y, w_m, w_c, w_s, w_d_geo, w_d_calendar, w_t)}

#: The same matrices in SQL, for the oracles.
MATRIX_SQL = {
    "w_r": """SELECT l_quantity AS qty, round(l_discount*100)::BIGINT AS disc_cents, p_size AS size, p_brand AS brand, p_type AS type, c_mktsegment AS segment, n_name AS nation, r_name AS region
        FROM lineitem JOIN orders ON l_orderkey=o_orderkey JOIN customer ON o_custkey=c_custkey JOIN nation ON c_nationkey=n_nationkey JOIN region ON n_regionkey=r_regionkey JOIN part ON l_partkey=p_partkey JOIN supplier ON l_suppkey=s_suppkey""",
    "w_f": """SELECT l_quantity AS units, (l_discount >= 0.07)::INT::VARCHAR AS promo, p_type AS class, p_retailprice AS price, n_name AS nation, tx.n AS tx_n, coalesce(oil.price, 0) AS oil, CASE WHEN oil.price IS NULL THEN '1' ELSE '0' END AS no_oil,
        (dayofweek(l_shipdate::DATE) IN (0,6))::INT::VARCHAR AS weekend
        FROM lineitem JOIN part ON l_partkey=p_partkey JOIN supplier ON l_suppkey=s_suppkey JOIN nation ON s_nationkey=n_nationkey
        JOIN (SELECT l_shipdate::DATE AS day, l_suppkey AS k, count(*) AS n FROM lineitem GROUP BY 1,2) tx ON tx.day=l_shipdate::DATE AND tx.k=l_suppkey
        LEFT JOIN (SELECT o_orderdate::DATE AS day, floor(avg(o_totalprice)) AS price FROM orders GROUP BY 1) oil ON oil.day=l_shipdate::DATE""",
    "w_y": """SELECT event_type, c_mktsegment AS segment, n_name AS nation, r_name AS region, o_orderpriority AS priority, o_orderstatus AS status, n_orders, round(value*100)::BIGINT AS value
        FROM events JOIN customer ON user_id=c_custkey JOIN orders o ON o.o_custkey=c_custkey JOIN (SELECT o_custkey AS k, count(*) AS n_orders FROM orders GROUP BY 1) t ON t.k=c_custkey JOIN nation ON c_nationkey=n_nationkey JOIN region ON n_regionkey=r_regionkey""",
    "w_m": """SELECT o_orderpriority AS priority, o_orderstatus AS status, c_mktsegment AS segment, s_suppkey::VARCHAR AS suppkey, n_name AS nation, r_name AS region
        FROM orders JOIN customer ON o_custkey=c_custkey JOIN nation ON c_nationkey=n_nationkey JOIN supplier ON s_nationkey=n_nationkey JOIN region ON n_regionkey=r_regionkey""",
    "w_c": """SELECT c_mktsegment AS segment, o_orderpriority AS priority, n_name AS nation, l_quantity AS qty
        FROM customer JOIN orders ON c_custkey=o_custkey JOIN lineitem ON o_orderkey=l_orderkey JOIN supplier ON l_suppkey=s_suppkey AND s_nationkey=c_nationkey JOIN nation ON c_nationkey=n_nationkey""",
    "w_s": "SELECT a.l_quantity AS qty_a, a.l_returnflag AS flag_a, b.l_quantity AS qty_b, b.l_returnflag AS flag_b FROM lineitem a JOIN lineitem b ON a.l_partkey=b.l_partkey",
    "w_d_geo": "SELECT c_custkey::VARCHAR AS custkey, n_name AS nation, r_name AS region FROM orders JOIN customer ON o_custkey=c_custkey JOIN nation ON c_nationkey=n_nationkey JOIN region ON n_regionkey=r_regionkey",
    "w_d_calendar": "SELECT o_orderdate::DATE::VARCHAR AS day, date_trunc('month', o_orderdate)::DATE::VARCHAR AS month, date_trunc('quarter', o_orderdate)::DATE::VARCHAR AS quarter, date_trunc('year', o_orderdate)::DATE::VARCHAR AS year FROM orders",
    "w_t": "SELECT n_chars, lang, source, quality::VARCHAR AS quality, toxic::VARCHAR AS toxic FROM documents JOIN labels USING (doc_id)",
}
MATRIX_SQL["w_f_lite"] = f"SELECT units, promo, class, weekend FROM ({MATRIX_SQL['w_f']})"
