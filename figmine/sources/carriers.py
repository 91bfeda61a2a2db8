"""Views of the given tables that play the entities of the chain: volumes, detections, crops, vectors, calls, run log."""

from __future__ import annotations

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F


def read(spark: SparkSession, sf_dir: str, table: str) -> DataFrame:
    return spark.read.parquet(f"{sf_dir}/{table}.parquet")


def unit_hash(key: str, salt: str):
    """A number in [0, 1) drawn from the md5 of key and salt; the same in every engine."""
    return F.conv(F.substring(F.md5(F.concat(F.col(key).cast("string"), F.lit(f":{salt}"))), 1, 8), 16, 10).cast("double") / F.lit(4294967296.0)


def volumes(spark: SparkSession, sf_dir: str) -> DataFrame:
    orders, customer, nation = (read(spark, sf_dir, t) for t in ("orders", "customer", "nation"))
    return (
        orders.join(customer, F.col("o_custkey") == F.col("c_custkey"))
        .join(F.broadcast(nation), F.col("c_nationkey") == F.col("n_nationkey"))
        .select(
            F.col("o_orderkey").alias("volume_id"),
            F.col("n_name").alias("language_src"),
            F.col("c_mktsegment").alias("topic"),
            F.when(F.col("o_orderkey") % 10 != 0, F.year("o_orderdate")).alias("date1_src"),
        )
    )


def detections(spark: SparkSession, sf_dir: str) -> DataFrame:
    line = read(spark, sf_dir, "lineitem")
    x0, y0 = F.col("l_partkey") % 997, (F.col("l_suppkey") * 13) % 1201
    width, height = 37 + F.floor("l_quantity") * 19, 21 + F.floor("l_extendedprice") % 1500
    confidence = F.lit(0.30) + F.lit(0.70) * ((31 * F.col("l_partkey") + 17 * F.col("l_suppkey") + 7 * F.col("l_linenumber")) % 1000) / F.lit(999.0)
    wrong = (13 * F.col("l_partkey") + 29 * F.col("l_linenumber") + F.floor("l_quantity")) % 1000
    label = (
        F.when((F.col("l_returnflag") == "N"), "illustration")
        .when((F.col("l_returnflag") == "A") & (F.col("l_linestatus") == "F"), "artifact")
        .when(F.col("l_returnflag") == "A", "decorative")
        .when((F.col("l_returnflag") == "R") & (F.col("l_linestatus") == "F"), "chart")
        .otherwise("music")
    )
    return line.select(
        F.concat_ws("-", "l_orderkey", "l_linenumber", "l_partkey", "l_suppkey", F.date_format("l_shipdate", "yyyyMMdd")).alias("key"),
        F.col("l_orderkey").alias("volume_id"),
        x0.alias("x0"),
        y0.alias("y0"),
        (x0 + width).alias("x1"),
        (y0 + height).alias("y1"),
        confidence.alias("detection_confidence"),
        label.alias("raw_class"),
        (F.lit(1.0) - (wrong * wrong) / F.lit(2000000.0)).alias("class_confidence"),
        F.col("l_shipdate").alias("shipped"),
    )


#: The same two views for DuckDB.
VOLUMES_SQL = """volumes AS (SELECT o_orderkey AS volume_id, n_name AS language_src, c_mktsegment AS topic, CASE WHEN o_orderkey % 10 <> 0 THEN year(o_orderdate) END AS date1_src
FROM orders JOIN customer ON o_custkey = c_custkey JOIN nation ON c_nationkey = n_nationkey)"""
DETECTIONS_SQL = """detections AS (SELECT l_orderkey AS volume_id, l_orderkey || '-' || l_linenumber || '-' || l_partkey || '-' || l_suppkey || '-' || strftime(l_shipdate, '%Y%m%d') AS key,
l_partkey % 997 AS x0, (l_suppkey * 13) % 1201 AS y0, l_partkey % 997 + 37 + floor(l_quantity)::BIGINT * 19 AS x1, (l_suppkey * 13) % 1201 + 21 + floor(l_extendedprice)::BIGINT % 1500 AS y1,
0.30::DOUBLE + 0.70::DOUBLE * ((31 * l_partkey + 17 * l_suppkey + 7 * l_linenumber) % 1000) / 999.0::DOUBLE AS detection_confidence,
CASE WHEN l_returnflag = 'N' THEN 'illustration' WHEN l_returnflag = 'A' AND l_linestatus = 'F' THEN 'artifact' WHEN l_returnflag = 'A' THEN 'decorative' WHEN l_returnflag = 'R' AND l_linestatus = 'F' THEN 'chart' ELSE 'music' END AS raw_class,
1.0::DOUBLE - power((13 * l_partkey + 29 * l_linenumber + floor(l_quantity)::BIGINT) % 1000, 2) / 2000000.0::DOUBLE AS class_confidence, l_shipdate AS shipped FROM lineitem)"""


def planted_vectors(spark: SparkSession, sf_dir: str) -> DataFrame:
    """(id, vec, truth_group): every seventh vector with 1 to 12 planted copies, each a little rotated and unit again."""
    base = read(spark, sf_dir, "embeddings").select("vec_id", F.transform("embedding", lambda x: x.cast("double")).alias("v"))
    copies = F.when(F.col("vec_id") % 7 == 0, F.col("vec_id").cast("long") / 7 % 12 + 1).otherwise(0).cast("int")
    rows = base.select("vec_id", "v", F.explode(F.sequence(F.lit(0), copies)).alias("k"))
    n = F.size("v")
    moved = F.transform("v", lambda x, i: x + F.lit(0.05) * F.col("k") * F.get(F.col("v"), (i + F.col("k")) % n))
    rows = rows.withColumn("m", moved).withColumn("norm", F.sqrt(F.aggregate("m", F.lit(0.0), lambda a, x: a + x * x)))
    return rows.select(F.concat_ws(":", "vec_id", "k").alias("id"), F.when(F.col("norm") > 0, F.transform("m", lambda x: x / F.col("norm"))).alias("vec"), F.col("vec_id").alias("truth_group"))


def caption_calls(spark: SparkSession, sf_dir: str) -> DataFrame:
    """User turns as requests; the assistant turn right after is the response, if there is one."""
    from pyspark.sql import Window

    order = Window.partitionBy("conv_id").orderBy("turn")
    rows = read(spark, sf_dir, "conversations").withColumn("next_role", F.lead("role").over(order)).withColumn("next_text", F.lead("text").over(order))
    return rows.where("role = 'user'").select("conv_id", "turn", F.col("text").alias("request"), F.when(F.col("next_role") == "assistant", F.col("next_text")).alias("response"))


def run_log(spark: SparkSession, sf_dir: str) -> DataFrame:
    events = read(spark, sf_dir, "events")
    return events.select(F.get_json_object("props", "$.k").cast("int").alias("batch"), F.col("event_type").alias("step"), F.col("ts").cast("timestamp").alias("started"), F.col("value").alias("seconds"), F.col("user_id").alias("worker"))
