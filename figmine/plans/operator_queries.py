"""Queries over the relational operators a user of the chain needs, each with its SQL."""

from __future__ import annotations

from pyspark.sql import Window
from pyspark.sql import functions as F

from ..sources.carriers import read

QUERIES: dict = {}
ORACLES: dict = {}


def operator(sql: str | None = None):
    def add(f):
        QUERIES[f.__name__] = f
        if sql:
            ORACLES[f.__name__] = sql
        return f

    return add


@operator("SELECT l_orderkey, l_quantity FROM lineitem WHERE l_quantity BETWEEN 10 AND 20 AND l_discount < 0.05")
def op_scan_filter_project(s, d):
    return read(s, d, "lineitem").where("l_quantity BETWEEN 10 AND 20 AND l_discount < 0.05").select("l_orderkey", "l_quantity")


@operator("SELECT doc_id FROM documents WHERE lang IN ('en', 'de') AND source LIKE 'src1%' AND regexp_matches(text, '[0-9]{3}') AND n_chars IS NOT NULL")
def op_filter_predicates(s, d):
    return read(s, d, "documents").where(F.col("lang").isin("en", "de") & F.col("source").like("src1%") & F.col("text").rlike("[0-9]{3}") & F.col("n_chars").isNotNull()).select("doc_id")


@operator("SELECT p_brand, count(*) AS n FROM lineitem JOIN part ON l_partkey = p_partkey GROUP BY 1")
def op_join_shuffle_hash(s, d):
    part = read(s, d, "part").select("p_partkey", "p_brand")
    return read(s, d, "lineitem").join(part.hint("shuffle_hash"), F.col("l_partkey") == F.col("p_partkey")).groupBy("p_brand").agg(F.count("*").alias("n"))


@operator("SELECT o_orderpriority, round(sum(l_quantity), 2) AS quantity FROM lineitem JOIN orders ON l_orderkey = o_orderkey GROUP BY 1")
def op_join_merge(s, d):
    return read(s, d, "lineitem").join(read(s, d, "orders").hint("merge"), F.col("l_orderkey") == F.col("o_orderkey")).groupBy("o_orderpriority").agg(F.round(F.sum("l_quantity"), 2).alias("quantity"))


@operator("SELECT count(*) AS n FROM orders WHERE EXISTS (SELECT 1 FROM lineitem WHERE l_orderkey = o_orderkey)")
def op_join_semi(s, d):
    return read(s, d, "orders").join(read(s, d, "lineitem"), F.col("l_orderkey") == F.col("o_orderkey"), "left_semi").agg(F.count("*").alias("n"))


@operator("SELECT o_orderkey FROM orders WHERE NOT EXISTS (SELECT 1 FROM lineitem WHERE l_orderkey = o_orderkey)")
def op_join_anti(s, d):
    return read(s, d, "orders").join(read(s, d, "lineitem"), F.col("l_orderkey") == F.col("o_orderkey"), "left_anti").select("o_orderkey")


@operator("SELECT coalesce(a.k, b.k) AS k, a.n AS customers, b.n AS suppliers FROM (SELECT c_nationkey AS k, count(*) AS n FROM customer WHERE c_acctbal > 9000 GROUP BY 1) a FULL JOIN (SELECT s_nationkey AS k, count(*) AS n FROM supplier WHERE s_acctbal > 5000 GROUP BY 1) b ON a.k = b.k")
def op_join_full_outer(s, d):
    a = read(s, d, "customer").where("c_acctbal > 9000").groupBy(F.col("c_nationkey").alias("k")).agg(F.count("*").alias("customers"))
    b = read(s, d, "supplier").where("s_acctbal > 5000").groupBy(F.col("s_nationkey").alias("k")).agg(F.count("*").alias("suppliers"))
    return a.join(b, "k", "full_outer").select("k", "customers", "suppliers")


@operator("SELECT e.event_id, (SELECT max(p.ts) FROM events p WHERE p.user_id = e.user_id AND p.event_type = 'error' AND p.ts < e.ts)::VARCHAR AS last_error FROM events e")
def op_join_asof(s, d):
    e = read(s, d, "events").withColumn("t", F.unix_micros(F.col("ts").cast("timestamp")))
    w = Window.partitionBy("user_id").orderBy("t").rangeBetween(Window.unboundedPreceding, -1)
    return e.select("event_id", F.max(F.when(F.col("event_type") == "error", F.col("ts"))).over(w).cast("string").alias("last_error"))


@operator("SELECT l_returnflag, count(*) AS n, round(sum(l_quantity), 2) AS s, round(avg(l_quantity), 6) AS a, min(l_quantity) AS lo, max(l_quantity) AS hi, count(DISTINCT l_suppkey) AS suppliers, count_if(l_discount > 0.05)::BIGINT AS discounted FROM lineitem GROUP BY 1")
def op_agg_basic(s, d):
    return read(s, d, "lineitem").groupBy("l_returnflag").agg(F.count("*").alias("n"), F.round(F.sum("l_quantity"), 2).alias("s"), F.round(F.avg("l_quantity"), 6).alias("a"), F.min("l_quantity").alias("lo"), F.max("l_quantity").alias("hi"), F.count_distinct("l_suppkey").alias("suppliers"), F.count_if(F.col("l_discount") > 0.05).alias("discounted"))


@operator("SELECT l_returnflag, l_linestatus, count(*) AS n FROM lineitem GROUP BY ROLLUP (l_returnflag, l_linestatus)")
def op_agg_rollup(s, d):
    return read(s, d, "lineitem").rollup("l_returnflag", "l_linestatus").agg(F.count("*").alias("n"))


@operator("SELECT l_returnflag, count_if(l_linestatus = 'F')::BIGINT AS \"F\", count_if(l_linestatus = 'O')::BIGINT AS \"O\" FROM lineitem GROUP BY 1")
def op_agg_pivot(s, d):
    p = read(s, d, "lineitem").groupBy("l_returnflag").pivot("l_linestatus", ["F", "O"]).agg(F.count(F.lit(1)))
    return p.select("l_returnflag", F.coalesce("F", F.lit(0)).alias("F"), F.coalesce("O", F.lit(0)).alias("O"))


@operator("SELECT l_shipdate::DATE::VARCHAR AS day, n, sum(n) OVER (ORDER BY l_shipdate::DATE ROWS UNBOUNDED PRECEDING)::BIGINT AS running, lag(n) OVER (ORDER BY l_shipdate::DATE) AS before FROM (SELECT l_shipdate::DATE AS l_shipdate, count(*) AS n FROM lineitem WHERE l_quantity = 1 GROUP BY 1)")
def op_win_running(s, d):
    g = read(s, d, "lineitem").where("l_quantity = 1").groupBy(F.to_date("l_shipdate").alias("day")).agg(F.count("*").alias("n"))
    w = Window.orderBy("day")
    return g.select(F.col("day").cast("string").alias("day"), "n", F.sum("n").over(w.rowsBetween(Window.unboundedPreceding, 0)).alias("running"), F.lag("n").over(w).alias("before"))


@operator("SELECT l_suppkey, l_extendedprice, r FROM (SELECT l_suppkey, l_extendedprice, rank() OVER (PARTITION BY l_suppkey ORDER BY l_extendedprice DESC)::INTEGER AS r FROM lineitem) WHERE r <= 3")
def op_topk_per_group(s, d):
    w = Window.partitionBy("l_suppkey").orderBy(F.desc("l_extendedprice"))
    return read(s, d, "lineitem").select("l_suppkey", "l_extendedprice", F.rank().over(w).alias("r")).where("r <= 3")


@operator("SELECT c_nationkey AS k FROM customer INTERSECT SELECT s_nationkey FROM supplier")
def op_set_intersect(s, d):
    return read(s, d, "customer").select(F.col("c_nationkey").alias("k")).intersect(read(s, d, "supplier").select("s_nationkey"))


@operator("SELECT n_nationkey AS k FROM nation EXCEPT SELECT s_nationkey FROM supplier WHERE s_acctbal > 9000")
def op_set_except(s, d):
    return read(s, d, "nation").select(F.col("n_nationkey").alias("k")).exceptAll(read(s, d, "supplier").where("s_acctbal > 9000").select("s_nationkey"))


@operator("SELECT page_id, regexp_extract(url, '^https?://([^/]+)', 1) AS host, length(regexp_replace(html, '<[^>]*>', '', 'g'))::INTEGER AS n FROM pages")
def op_html_text(s, d):
    return read(s, d, "pages").select("page_id", F.regexp_extract("url", "^https?://([^/]+)", 1).alias("host"), F.length(F.regexp_replace("html", "<[^>]*>", "")).alias("n"))


@operator("SELECT event_id, CAST(json_extract(props, '$.k') AS INTEGER) AS k FROM events")
def op_json(s, d):
    return read(s, d, "events").select("event_id", F.from_json("props", "k INT")["k"].alias("k"))


@operator("SELECT vec_id, round(list_inner_product(embedding, embedding), 4)::DOUBLE AS size FROM embeddings")
def op_array_hof(s, d):
    return read(s, d, "embeddings").select("vec_id", F.round(F.aggregate("embedding", F.lit(0.0), lambda a, x: a + x.cast("double") * x.cast("double")), 4).alias("size"))


@operator("SELECT doc_id FROM documents ORDER BY md5(doc_id::VARCHAR) LIMIT 100")
def op_sample_md5(s, d):
    return read(s, d, "documents").select("doc_id").orderBy(F.md5(F.col("doc_id").cast("string"))).limit(100)
