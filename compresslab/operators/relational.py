"""The engine's surrounding relational operators on the star schema: rollups, semi and anti joins, set operations,
bands, frames, pivots, distinct counts, strings and dates, arrays, maps and JSON."""

from __future__ import annotations

from pyspark.sql import DataFrame, SparkSession, Window
from pyspark.sql import functions as F

from ..sources.tables import table


def pricing_rollup(spark: SparkSession, sf_dir: str) -> DataFrame:
    l = table(spark, sf_dir, "lineitem").where(F.col("l_shipdate") <= F.lit("1998-09-02").cast("timestamp_ntz"))  # noqa: E741
    return l.rollup("l_returnflag", "l_linestatus").agg(
        F.round(F.sum("l_quantity"), 2).alias("sum_qty"), F.round(F.sum(F.col("l_extendedprice") * (1 - F.col("l_discount"))), 2).alias("revenue"),
        F.round(F.avg("l_discount"), 6).alias("avg_disc"), F.count("*").alias("n"))


def cube_segments(spark, sf_dir) -> DataFrame:
    c, n, r = (table(spark, sf_dir, t) for t in ("customer", "nation", "region"))
    j = c.join(F.broadcast(n), c.c_nationkey == n.n_nationkey).join(F.broadcast(r), n.n_regionkey == r.r_regionkey)
    return j.cube("r_name", "c_mktsegment").agg(F.grouping_id().cast("long").alias("level"), F.count("*").alias("n"), F.round(F.sum("c_acctbal"), 2).alias("balance"))


def grouping_sets(spark, sf_dir) -> DataFrame:
    table(spark, sf_dir, "orders").createOrReplaceTempView("compresslab_orders")
    return spark.sql("""SELECT o_orderstatus, o_orderpriority, count(*) AS n, round(sum(o_totalprice), 2) AS total FROM compresslab_orders
        GROUP BY GROUPING SETS ((o_orderstatus), (o_orderpriority), (o_orderstatus, o_orderpriority), ())""")


def top_customers(spark, sf_dir) -> DataFrame:
    c, o, l = (table(spark, sf_dir, t) for t in ("customer", "orders", "lineitem"))  # noqa: E741
    spent = l.groupBy("l_orderkey").agg(F.sum(F.col("l_extendedprice") * (1 - F.col("l_discount"))).alias("v")).join(o, F.col("l_orderkey") == o.o_orderkey)
    by = spent.groupBy("o_custkey").agg(F.round(F.sum("v"), 2).alias("revenue"), F.count("*").alias("orders"))
    return by.join(c, by.o_custkey == c.c_custkey).select("c_custkey", "c_name", "revenue", "orders").orderBy(F.desc("revenue"), "c_custkey").limit(50)


def semi_anti(spark, sf_dir) -> DataFrame:
    c, o = table(spark, sf_dir, "customer"), table(spark, sf_dir, "orders")
    big = o.where("o_totalprice > 300000").select("o_custkey")
    semi = c.join(big, c.c_custkey == big.o_custkey, "left_semi").groupBy("c_mktsegment").agg(F.count("*").alias("n")).withColumn("side", F.lit("with_big_order"))
    anti = c.join(o, c.c_custkey == o.o_custkey, "left_anti").groupBy("c_mktsegment").agg(F.count("*").alias("n")).withColumn("side", F.lit("without_order"))
    return semi.unionByName(anti)


def set_ops(spark, sf_dir) -> DataFrame:
    l = table(spark, sf_dir, "lineitem")  # noqa: E741
    cheap, many = l.where("l_discount < 0.03").select("l_suppkey", "l_returnflag"), l.where("l_quantity > 45").select("l_suppkey", "l_returnflag")
    both = cheap.intersect(many).withColumn("op", F.lit("intersect"))
    only = cheap.distinct().exceptAll(many.distinct()).withColumn("op", F.lit("except"))
    return both.unionByName(only)


def theta_band(spark, sf_dir) -> DataFrame:
    """Price bands by a range join, as an equi-join on coarse buckets followed by the exact condition."""
    p = table(spark, sf_dir, "part").select("p_partkey", "p_retailprice")
    bands = spark.range(0, 40).select((F.col("id") * 75).cast("double").alias("low"), ((F.col("id") + 1) * 75).cast("double").alias("high"))
    width = 75.0
    left = p.withColumn("bucket", F.floor(F.col("p_retailprice") / width))
    right = bands.withColumn("bucket", F.explode(F.sequence(F.floor(F.col("low") / width), F.floor(F.col("high") / width))))
    j = left.join(F.broadcast(right), "bucket").where("p_retailprice >= low AND p_retailprice < high")
    return j.groupBy("low", "high").agg(F.count("*").alias("n"), F.round(F.avg("p_retailprice"), 6).alias("mean_price"))


def window_frames(spark, sf_dir) -> DataFrame:
    o = table(spark, sf_dir, "orders")
    w = Window.partitionBy("o_custkey").orderBy("o_orderdate", "o_orderkey")
    return o.select(
        "o_orderkey", F.row_number().over(w).alias("nth"), F.round(F.sum("o_totalprice").over(w.rowsBetween(-2, 0)), 2).alias("last_three"),
        F.round(F.col("o_totalprice") - F.lag("o_totalprice").over(w), 2).alias("change"), F.ntile(4).over(Window.partitionBy("o_custkey").orderBy("o_totalprice", "o_orderkey")).alias("quarter"),
        F.round(F.percent_rank().over(Window.partitionBy("o_orderstatus").orderBy("o_totalprice", "o_orderkey")), 9).alias("pr"))


def pivot_status(spark, sf_dir) -> DataFrame:
    l = table(spark, sf_dir, "lineitem")  # noqa: E741
    wide = l.groupBy("l_returnflag").pivot("l_linestatus", ["F", "O"]).agg(F.round(F.sum("l_quantity"), 2))
    return wide.unpivot("l_returnflag", ["F", "O"], "l_linestatus", "sum_qty")


def distinct_counts(spark, sf_dir) -> DataFrame:
    l = table(spark, sf_dir, "lineitem")  # noqa: E741
    return l.groupBy("l_returnflag").agg(F.countDistinct("l_suppkey").alias("suppliers"), F.countDistinct("l_partkey", "l_suppkey").alias("pairs"))


def distinct_approx(spark, sf_dir) -> DataFrame:
    """Exact counts, and whether the two sketches are within 8 % of them (four standard errors)."""
    l = table(spark, sf_dir, "lineitem")  # noqa: E741
    found = l.groupBy("l_returnflag").agg(
        F.approx_count_distinct("l_partkey", 0.02).alias("approx"), F.hll_sketch_estimate(F.hll_sketch_agg("l_partkey")).alias("hll"), F.countDistinct("l_partkey").alias("exact"))
    close = lambda c: (F.abs(F.col(c) - F.col("exact")) <= 0.08 * F.col("exact")).alias(f"{c}_close")
    return found.select("l_returnflag", "exact", close("approx"), close("hll"))


def string_date_math(spark, sf_dir) -> DataFrame:
    o, c = table(spark, sf_dir, "orders"), table(spark, sf_dir, "customer")
    j = o.join(c, o.o_custkey == c.c_custkey)
    return j.groupBy(F.date_trunc("month", "o_orderdate").cast("date").alias("month"), F.lower(F.substring("c_mktsegment", 1, 4)).alias("segment")).agg(
        F.count("*").alias("n"), F.round(F.sqrt(F.sum(F.col("o_totalprice") * F.col("o_totalprice"))), 4).alias("root"), F.max(F.length(F.regexp_replace("c_name", "[^0-9]", ""))).alias("digits"),
        F.min(F.levenshtein("c_mktsegment", F.lit("BUILDING"))).alias("edits"))


def array_map_json(spark, sf_dir) -> DataFrame:
    """Sums and the first ten of each type; a limit on ranks cuts every partition to ten rows before the shuffle."""
    e = table(spark, sf_dir, "events").select("event_type", "event_id", F.get_json_object("props", "$.k").cast("int").alias("k"))
    sums = e.groupBy("event_type").agg(F.sum("k").alias("sum_k"), F.size(F.collect_set("k")).alias("distinct_k"), F.min("event_id").alias("first_id"))
    first = e.withColumn("place", F.row_number().over(Window.partitionBy("event_type").orderBy("event_id"))).where("place <= 10")
    ten = first.groupBy("event_type").agg(F.aggregate(F.sort_array(F.collect_list("event_id")), F.lit(0).cast("long"), lambda a, x: a + x).alias("sum_first_ten"))
    return sums.join(ten, "event_type")


def join_hints(spark, sf_dir) -> DataFrame:
    """One join by each physical strategy: the plans differ, the rows do not."""
    o, c = table(spark, sf_dir, "orders").select("o_custkey", "o_totalprice"), table(spark, sf_dir, "customer").select("c_custkey", "c_mktsegment")
    found = None
    for hint in ("broadcast", "merge", "shuffle_hash"):
        own = o.join(c.hint(hint), F.col("o_custkey") == F.col("c_custkey")).groupBy("c_mktsegment").agg(F.count("*").alias("n"), F.round(F.sum("o_totalprice"), 2).alias("total")).withColumn("strategy", F.lit(hint))
        found = own if found is None else found.unionByName(own)
    return found
