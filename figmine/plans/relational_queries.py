"""More operators a user of the chain needs: joins of other kinds, sets of groupings, sketches, windows, texts, functions."""

from __future__ import annotations

import pandas as pd
import pyarrow as pa
import pyarrow.compute as pc
from pyspark.sql import Window
from pyspark.sql import functions as F
from pyspark.sql.types import Row

from ..functions.expressions import band_keys, dot, iou
from ..sources import carriers as C
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


# ---- joins


@operator("SELECT n_name, count(*) AS n FROM customer JOIN nation ON c_nationkey = n_nationkey GROUP BY 1")
def op_join_broadcast(s, d):
    # nation has a row a country whatever the scale
    return read(s, d, "customer").join(F.broadcast(read(s, d, "nation")), F.col("c_nationkey") == F.col("n_nationkey")).groupBy("n_name").agg(F.count("*").alias("n"))


@operator("SELECT n_name, count(s_suppkey) AS suppliers FROM nation LEFT JOIN supplier ON n_nationkey = s_nationkey GROUP BY 1")
def op_join_left_outer(s, d):
    counts = read(s, d, "supplier").groupBy("s_nationkey").agg(F.count("*").alias("n"))
    return read(s, d, "nation").join(counts, F.col("n_nationkey") == F.col("s_nationkey"), "left").select("n_name", F.coalesce("n", F.lit(0)).alias("suppliers"))


@operator("SELECT cut, count_if(l_discount >= cut / 100.0::DOUBLE)::BIGINT AS kept FROM lineitem, (SELECT unnest(range(0, 11)) AS cut) GROUP BY 1")
def op_join_cross(s, d):
    # a grid of eleven cuts against pre-aggregated rows, not against every row
    rows = read(s, d, "lineitem").groupBy("l_discount").agg(F.count("*").alias("n"))
    grid = s.range(11).withColumnRenamed("id", "cut")
    return rows.crossJoin(F.broadcast(grid)).groupBy("cut").agg(F.sum(F.when(F.col("l_discount") >= F.col("cut") / 100.0, F.col("n")).otherwise(0)).alias("kept"))


@operator(f"WITH {C.DETECTIONS_SQL} SELECT a.volume_id, a.key AS left_key, b.key AS right_key FROM detections a JOIN detections b ON a.volume_id = b.volume_id AND a.key < b.key AND a.x0 < b.x1 AND b.x0 < a.x1 AND a.y0 < b.y1 AND b.y0 < a.y1")
def op_join_theta(s, d):
    rows = C.detections(s, d).select("volume_id", "key", "x0", "y0", "x1", "y1")
    a, b = rows.alias("a"), rows.alias("b")
    meet = (F.col("a.volume_id") == F.col("b.volume_id")) & (F.col("a.key") < F.col("b.key"))
    for lo, hi in (("x0", "x1"), ("y0", "y1")):
        meet &= (F.col(f"a.{lo}") < F.col(f"b.{hi}")) & (F.col(f"b.{lo}") < F.col(f"a.{hi}"))
    return a.join(b, meet).select("a.volume_id", F.col("a.key").alias("left_key"), F.col("b.key").alias("right_key"))


@operator("WITH spans AS (SELECT event_id AS span, user_id, ts AS lo, ts + INTERVAL 10 MINUTE AS hi FROM events WHERE event_type = 'error') SELECT span, count(*) AS inside FROM spans JOIN events e ON e.user_id = spans.user_id AND e.ts >= lo AND e.ts < hi GROUP BY 1")
def op_join_range(s, d):
    """Events inside an interval of the same worker: both sides carry the ten-minute bins they touch, so the join is by equality."""
    micros = F.unix_micros(F.col("ts").cast("timestamp"))
    e = read(s, d, "events").select("event_id", "user_id", "event_type", micros.alias("t"))
    width = 600_000_000
    spans = e.where("event_type = 'error'").select(F.col("event_id").alias("span"), "user_id", F.col("t").alias("lo"), F.explode(F.array(F.floor(F.col("t") / width), F.floor(F.col("t") / width) + 1)).alias("bin"))
    points = e.select("user_id", "t", F.floor(F.col("t") / width).alias("bin"))
    return spans.join(points, ["user_id", "bin"]).where((F.col("t") >= F.col("lo")) & (F.col("t") < F.col("lo") + width)).groupBy("span").agg(F.count("*").alias("inside"))


# ---- aggregates


@operator("SELECT l_returnflag, count(DISTINCT l_partkey) AS parts, count(DISTINCT l_suppkey) AS suppliers FROM lineitem GROUP BY 1")
def op_agg_distinct(s, d):
    return read(s, d, "lineitem").groupBy("l_returnflag").agg(F.count_distinct("l_partkey").alias("parts"), F.count_distinct("l_suppkey").alias("suppliers"))


@operator("SELECT l_linestatus, count(*) FILTER (l_discount > 0.05) AS cheap, round(sum(l_quantity) FILTER (l_tax = 0), 2) AS untaxed FROM lineitem GROUP BY 1")
def op_agg_conditional(s, d):
    return read(s, d, "lineitem").groupBy("l_linestatus").agg(F.expr("count(*) FILTER (WHERE l_discount > 0.05)").alias("cheap"), F.expr("round(sum(l_quantity) FILTER (WHERE l_tax = 0), 2)").alias("untaxed"))


@operator(f"WITH {C.VOLUMES_SQL} SELECT language_src, topic, count(*) AS n FROM volumes GROUP BY CUBE (language_src, topic)")
def op_agg_cube(s, d):
    return C.volumes(s, d).cube("language_src", "topic").agg(F.count("*").alias("n"))


@operator("SELECT l_returnflag, l_linestatus, count(*) AS n FROM lineitem GROUP BY GROUPING SETS ((l_returnflag), (l_linestatus), ())")
def op_agg_grouping_sets(s, d):
    return s.sql("SELECT l_returnflag, l_linestatus, count(*) AS n FROM {rows} GROUP BY GROUPING SETS ((l_returnflag), (l_linestatus), ())", rows=read(s, d, "lineitem"))


@operator("SELECT l_returnflag, 'quantity' AS measure, round(sum(l_quantity), 2) AS total FROM lineitem GROUP BY 1 UNION ALL SELECT l_returnflag, 'discount', round(sum(l_discount), 2) FROM lineitem GROUP BY 1")
def op_agg_unpivot(s, d):
    g = read(s, d, "lineitem").groupBy("l_returnflag").agg(F.round(F.sum("l_quantity"), 2).alias("quantity"), F.round(F.sum("l_discount"), 2).alias("discount"))
    return g.unpivot("l_returnflag", ["quantity", "discount"], "measure", "total")


@operator(f"WITH {C.DETECTIONS_SQL} SELECT raw_class, quantile_cont(x1 - x0, 0.25)::DOUBLE AS low, quantile_cont(x1 - x0, 0.5)::DOUBLE AS middle, quantile_cont(x1 - x0, 0.9)::DOUBLE AS high FROM detections GROUP BY 1")
def op_agg_percentile(s, d):
    w = F.col("x1") - F.col("x0")
    return C.detections(s, d).groupBy("raw_class").agg(*[F.percentile(w, F.lit(p)).alias(n) for n, p in (("low", 0.25), ("middle", 0.5), ("high", 0.9))])


@operator("SELECT lang, source FROM (SELECT lang, source, row_number() OVER (PARTITION BY lang ORDER BY n DESC, source) AS r FROM (SELECT lang, source, count(*) AS n FROM documents GROUP BY 1, 2)) WHERE r = 1")
def op_agg_mode(s, d):
    """The commonest source of each language, ties to the smallest: a mode that does not depend on the order of rows."""
    counts = read(s, d, "documents").groupBy("lang", "source").agg(F.count("*").alias("n"))
    return counts.groupBy("lang").agg(F.min_by("source", F.struct(-F.col("n"), "source")).alias("source"))


@operator("SELECT l_suppkey, arg_max(l_orderkey, l_orderkey) AS last_order, max(l_extendedprice) AS price FROM lineitem GROUP BY 1")
def op_agg_maxby(s, d):
    return read(s, d, "lineitem").groupBy("l_suppkey").agg(F.max_by("l_orderkey", "l_orderkey").alias("last_order"), F.max("l_extendedprice").alias("price"))


@operator("SELECT r_name, string_agg(n_name, ',' ORDER BY n_name) AS nations FROM region JOIN nation ON r_regionkey = n_regionkey GROUP BY 1")
def op_agg_listagg(s, d):
    j = read(s, d, "nation").join(F.broadcast(read(s, d, "region")), F.col("n_regionkey") == F.col("r_regionkey"))
    return s.sql("SELECT r_name, listagg(n_name, ',') WITHIN GROUP (ORDER BY n_name) AS nations FROM {j} GROUP BY r_name", j=j)


@operator()
def op_agg_approx(s, d):
    """Sketches and their exact twins; the tests hold their errors against the stated bounds."""
    return read(s, d, "lineitem").agg(
        F.approx_count_distinct("l_partkey", 0.02).alias("parts_near"),
        F.count_distinct("l_partkey").alias("parts"),
        F.hll_sketch_estimate(F.hll_sketch_agg("l_orderkey", 14)).alias("orders_near"),
        F.count_distinct("l_orderkey").alias("orders"),
        F.percentile_approx("l_extendedprice", 0.5, 10_000).alias("price_near"),
        F.percentile("l_extendedprice", F.lit(0.5)).alias("price"),
        F.size(F.histogram_numeric("l_quantity", F.lit(10))).alias("bins"),
    )


# ---- windows


@operator("SELECT c_custkey, rank() OVER w::INTEGER AS place, dense_rank() OVER w::INTEGER AS step, round(percent_rank() OVER w, 6) AS share FROM customer WINDOW w AS (PARTITION BY c_nationkey ORDER BY c_acctbal DESC)")
def op_win_rank(s, d):
    w = Window.partitionBy("c_nationkey").orderBy(F.desc("c_acctbal"))
    return read(s, d, "customer").select("c_custkey", F.rank().over(w).alias("place"), F.dense_rank().over(w).alias("step"), F.round(F.percent_rank().over(w), 6).alias("share"))


@operator("SELECT event_id, lag(event_type) OVER w AS before, lead(event_type, 2, 'none') OVER w AS later, first_value(event_type) OVER w AS first FROM events WINDOW w AS (PARTITION BY user_id ORDER BY event_id)")
def op_win_lag_lead(s, d):
    w = Window.partitionBy("user_id").orderBy("event_id")
    return read(s, d, "events").select("event_id", F.lag("event_type").over(w).alias("before"), F.lead("event_type", 2, "none").over(w).alias("later"), F.first("event_type").over(w).alias("first"))


@operator("SELECT p_partkey, ntile(4) OVER (PARTITION BY p_brand ORDER BY p_retailprice, p_partkey)::INTEGER AS quarter FROM part")
def op_win_ntile(s, d):
    return read(s, d, "part").select("p_partkey", F.ntile(4).over(Window.partitionBy("p_brand").orderBy("p_retailprice", "p_partkey")).alias("quarter"))


@operator("SELECT p_brand, p_type, round(count(*) / sum(count(*)) OVER (PARTITION BY p_brand), 6)::DOUBLE AS share FROM part GROUP BY 1, 2")
def op_win_ratio(s, d):
    g = read(s, d, "part").groupBy("p_brand", "p_type").agg(F.count("*").alias("n"))
    return g.select("p_brand", "p_type", F.round(F.col("n") / F.sum("n").over(Window.partitionBy("p_brand")), 6).alias("share"))


@operator("SELECT event_id, count(*) OVER (PARTITION BY user_id ORDER BY ts RANGE BETWEEN INTERVAL 1 HOUR PRECEDING AND CURRENT ROW) AS recent FROM events")
def op_win_range_frame(s, d):
    e = read(s, d, "events").withColumn("t", F.unix_micros(F.col("ts").cast("timestamp")))
    return e.select("event_id", F.count("*").over(Window.partitionBy("user_id").orderBy("t").rangeBetween(-3_600_000_000, 0)).alias("recent"))


# ---- order, limits, sets


@operator("SELECT l_orderkey, l_linenumber, l_extendedprice FROM lineitem ORDER BY l_extendedprice DESC, l_orderkey, l_linenumber, l_partkey LIMIT 20")
def op_topk(s, d):
    return read(s, d, "lineitem").orderBy(F.desc("l_extendedprice"), "l_orderkey", "l_linenumber", "l_partkey").limit(20).select("l_orderkey", "l_linenumber", "l_extendedprice")


@operator("SELECT c_custkey FROM customer ORDER BY c_custkey LIMIT 25 OFFSET 50")
def op_offset(s, d):
    return read(s, d, "customer").select("c_custkey").orderBy("c_custkey").offset(50).limit(25)


@operator("SELECT c_nationkey AS k, 'customer' AS who FROM customer UNION SELECT s_nationkey, 'supplier' FROM supplier")
def op_set_union(s, d):
    a = read(s, d, "customer").select(F.col("c_nationkey").alias("k"), F.lit("customer").alias("who"))
    return a.unionByName(read(s, d, "supplier").select(F.lit("supplier").alias("who"), F.col("s_nationkey").alias("k"))).distinct()


# ---- texts


@operator("SELECT c_custkey, upper(substr(c_name, 1, 8)) AS head, reverse(c_name) AS back, lpad(c_custkey::VARCHAR, 8, '0') AS padded, replace(c_mktsegment, 'A', 'a') AS changed, levenshtein(c_name, 'Customer#1')::INTEGER AS far, md5(c_name) AS digest, strpos(c_name, '#')::INTEGER AS at FROM customer")
def op_str(s, d):
    name = F.col("c_name")
    return read(s, d, "customer").select("c_custkey", F.upper(F.substring(name, 1, 8)).alias("head"), F.reverse(name).alias("back"), F.lpad(F.col("c_custkey").cast("string"), 8, "0").alias("padded"), F.replace(F.col("c_mktsegment"), F.lit("A"), F.lit("a")).alias("changed"), F.levenshtein(name, F.lit("Customer#1")).alias("far"), F.md5(name).alias("digest"), F.instr(name, "#").alias("at"))


@operator("SELECT doc_id, len(regexp_extract_all(text, '[0-9]+'))::INTEGER AS numbers, regexp_extract(text, '([a-z]+)@', 1) AS account, regexp_matches(text, '^[A-Z]') AS capital FROM documents")
def op_regex(s, d):
    return read(s, d, "documents").select("doc_id", F.regexp_count("text", F.lit("[0-9]+")).alias("numbers"), F.regexp_extract("text", "([a-z]+)@", 1).alias("account"), F.col("text").rlike("^[A-Z]").alias("capital"))


@operator("SELECT page_id, regexp_extract(url, '^([a-z]+)://', 1) AS scheme, regexp_extract(url, '^[a-z]+://([^/]+)', 1) AS host, regexp_extract(url, '^[a-z]+://[^/]+([^?#]*)', 1) AS path FROM pages")
def op_url_parts(s, d):
    part = lambda p: F.coalesce(F.try_parse_url("url", F.lit(p)), F.lit(""))
    return read(s, d, "pages").select("page_id", part("PROTOCOL").alias("scheme"), part("HOST").alias("host"), part("PATH").alias("path"))


@operator(r"WITH w AS (SELECT item_id, list_filter(regexp_split_to_array(lower(text), '\s+'), lambda x: x <> '') AS w FROM benchmark), g AS (SELECT DISTINCT item_id, array_to_string(w[i:i + 2], ' ') AS gram FROM (SELECT item_id, w, unnest(range(1, greatest(len(w) - 2, 1) + 1)) AS i FROM w WHERE len(w) > 0)), n AS (SELECT item_id, count(*) AS n FROM g GROUP BY 1), p AS (SELECT a.item_id AS x, b.item_id AS y, count(*) AS common FROM g a JOIN g b ON a.gram = b.gram AND a.item_id < b.item_id GROUP BY 1, 2) SELECT x, y, round(common / (a.n + b.n - common), 6)::DOUBLE AS jaccard FROM p JOIN n a ON a.item_id = x JOIN n b ON b.item_id = y")
def op_shingles(s, d):
    words = F.filter(F.split(F.lower("text"), r"\s+"), lambda w: w != "")
    rows = read(s, d, "benchmark").select("item_id", words.alias("w")).where(F.size("w") > 0)
    grams = F.array_distinct(F.transform(F.sequence(F.lit(1), F.greatest(F.size("w") - 2, F.lit(1))), lambda i: F.array_join(F.slice("w", i, 3), " ")))
    g = rows.select("item_id", grams.alias("g")).select("item_id", F.size("g").alias("n"), F.explode("g").alias("gram"))
    a, b = (g.select(*[F.col(c).alias(c if c == "gram" else c + k) for c in g.columns]) for k in ("_a", "_b"))
    p = a.join(b, "gram").where("item_id_a < item_id_b").groupBy(F.col("item_id_a").alias("x"), F.col("item_id_b").alias("y"), "n_a", "n_b").agg(F.count("*").alias("both"))
    return p.select("x", "y", F.round(F.col("both") / (F.col("n_a") + F.col("n_b") - F.col("both")), 6).alias("jaccard"))


# ---- dates, numbers, nested values


@operator("SELECT o_orderkey, year(o_orderdate)::INTEGER AS y, (year(o_orderdate) // 100)::INTEGER AS hundred, strftime(date_trunc('quarter', o_orderdate), '%Y-%m-%d') AS quarter, (o_orderdate::DATE - DATE '1992-01-01')::INTEGER AS days, strftime(o_orderdate + INTERVAL 1 MONTH, '%Y-%m') AS next_month FROM orders")
def op_date(s, d):
    t = F.col("o_orderdate")
    return read(s, d, "orders").select("o_orderkey", F.year(t).alias("y"), F.floor(F.year(t) / 100).cast("int").alias("hundred"), F.date_format(F.date_trunc("quarter", t), "yyyy-MM-dd").alias("quarter"), F.date_diff(t, F.lit("1992-01-01").cast("date")).alias("days"), F.date_format(F.add_months(t, 1), "yyyy-MM").alias("next_month"))


@operator("SELECT p_partkey, bit_count(xor(p_partkey, 12345))::INTEGER AS bits, (p_partkey << 3)::BIGINT AS up, (p_partkey >> 2)::BIGINT AS down, round(ln(p_retailprice), 6) AS log, round(sqrt(p_retailprice), 6) AS root, greatest(0, least(11, floor((p_retailprice - 900) / 100)::BIGINT + 1))::BIGINT AS bin, ((p_partkey % 7) + 7) % 7 AS rest FROM part")
def op_math_bits(s, d):
    k, p = F.col("p_partkey"), F.col("p_retailprice")
    return read(s, d, "part").select("p_partkey", F.bit_count(k.bitwiseXOR(F.lit(12345).cast("bigint"))).alias("bits"), F.shiftleft(k, 3).alias("up"), F.shiftright(k, 2).alias("down"), F.round(F.ln(p), 6).alias("log"), F.round(F.sqrt(p), 6).alias("root"), F.width_bucket(p, F.lit(900.0), F.lit(1900.0), F.lit(10)).alias("bin"), F.pmod(k, F.lit(7)).alias("rest"))


@operator("SELECT (i - 1)::INTEGER AS place, count(*) AS n, count_if(x > 0)::BIGINT AS above FROM (SELECT unnest(embedding) AS x, generate_subscripts(embedding, 1) AS i FROM embeddings) GROUP BY 1")
def op_array_explode(s, d):
    return read(s, d, "embeddings").select(F.posexplode("embedding").alias("place", "x")).groupBy("place").agg(F.count("*").alias("n"), F.count_if(F.col("x") > 0).alias("above"))


@operator("SELECT lang, source, count(*) AS n FROM documents WHERE lang IS NOT NULL AND source IS NOT NULL GROUP BY 1, 2")
def op_map_nested(s, d):
    """Counts nested as a map of maps, and taken apart again for the comparison."""
    counts = read(s, d, "documents").where("lang IS NOT NULL AND source IS NOT NULL").groupBy("lang", "source").agg(F.count("*").alias("n"))
    inner = counts.groupBy("lang").agg(F.map_from_entries(F.collect_list(F.struct("source", "n"))).alias("m"))
    nested = inner.agg(F.map_from_entries(F.collect_list(F.struct("lang", "m"))).alias("m"))
    return nested.select(F.explode("m").alias("lang", "m")).select("lang", F.explode("m").alias("source", "n"))


@operator("SELECT event_id, CAST(json_extract(props, '$.k') AS BIGINT) AS k, json_extract(props, '$.absent') IS NULL AS absent FROM events")
def op_variant(s, d):
    v = F.try_parse_json("props")
    return read(s, d, "events").select("event_id", F.try_variant_get(v, "$.k", "bigint").alias("k"), F.try_variant_get(v, "$.absent", "string").isNull().alias("absent"))


@operator("WITH RECURSIVE e AS (SELECT DISTINCT n_nationkey AS a, (n_nationkey + 5) % 25 AS b FROM nation), both_ways AS (SELECT a, b FROM e UNION SELECT b, a FROM e), reach(node, far) AS (SELECT a, a FROM both_ways UNION SELECT reach.node, both_ways.b FROM reach JOIN both_ways ON reach.far = both_ways.a) SELECT node, min(far)::INTEGER AS component FROM reach GROUP BY 1")
def op_recursive_cc(s, d):
    """Components by a recursive query, for small graphs: ``operators.graph.components`` is the form for large ones."""
    nation = read(s, d, "nation").select("n_nationkey")
    return s.sql(
        """WITH RECURSIVE e AS (SELECT n_nationkey AS a, CAST((n_nationkey + 5) % 25 AS INT) AS b FROM {nation}), w AS (SELECT a, b FROM e UNION SELECT b, a FROM e),
        reach(node, far, hops) MAX RECURSION LEVEL 30 AS (SELECT a, a, 0 FROM w UNION ALL SELECT reach.node, w.b, hops + 1 FROM reach JOIN w ON reach.far = w.a WHERE hops < 4)
        SELECT node, min(far) AS component FROM reach GROUP BY node""",
        nation=nation,
    )


# ---- functions in Python, batch by batch


@operator("SELECT doc_id, length(coalesce(text, ''))::BIGINT AS n FROM documents")
def op_udf_arrow(s, d):
    @F.arrow_udf("bigint")
    def size(texts: pa.Array) -> pa.Array:
        return pc.cast(pc.utf8_length(pc.fill_null(texts, "")), pa.int64())

    return read(s, d, "documents").select("doc_id", size("text").alias("n"))


@operator("SELECT l_orderkey, l_linenumber, l_partkey, round(l_extendedprice * (1 - l_discount), 4) AS net FROM lineitem")
def op_udf_pandas(s, d):
    @F.pandas_udf("double")
    def net(price: pd.Series, discount: pd.Series) -> pd.Series:
        return price * (1 - discount)

    return read(s, d, "lineitem").select("l_orderkey", "l_linenumber", "l_partkey", F.round(net("l_extendedprice", "l_discount"), 4).alias("net"))


@operator("SELECT label, (i - 1)::INTEGER AS place, round(avg(x), 4) AS mean FROM (SELECT label, unnest(embedding)::DOUBLE AS x, generate_subscripts(embedding, 1) AS i FROM embeddings) GROUP BY 1, 2")
def op_udaf_centroid(s, d):
    """Centroid of each label: sums by place are combined before the shuffle, so no label's vectors meet in one task."""
    rows = read(s, d, "embeddings").select("label", F.posexplode("embedding").alias("place", "x"))
    return rows.groupBy("label", "place").agg(F.round(F.avg(F.col("x").cast("double")), 4).alias("mean"))


@operator("SELECT doc_id, (k - 1)::INTEGER AS band, substr(md5(coalesce(text, '')), ((k - 1) * 6 + 1)::INTEGER, 6) AS value FROM documents, (SELECT unnest(range(1, 6)) AS k)")
def op_udtf_bands(s, d):
    hashed = read(s, d, "documents").select("doc_id", F.md5(F.coalesce("text", F.lit(""))).alias("hash"))
    return hashed.select("doc_id", F.inline(band_keys(F.col("hash"), 5, 24))).select("doc_id", F.col("band").cast("int").alias("band"), "value")


@operator(r"SELECT page_id, i::INTEGER AS place, regexp_extract(b, '^<([a-z0-9]+)', 1) AS tag FROM (SELECT page_id, unnest(bs) AS b, generate_subscripts(bs, 1) AS i FROM (SELECT page_id, regexp_extract_all(html, '<(?:nav|footer|article|h1|script|style)[ >]') AS bs FROM pages))")
def op_udtf_blocks(s, d):
    """A table function in Python, called from SQL with a lateral join."""
    import re

    @F.udtf(returnType="place int, tag string")
    class Blocks:
        def eval(self, html: str):
            for k, m in enumerate(re.findall(r"<(nav|footer|article|h1|script|style)[ >]", html or "")):
                yield Row(place=k + 1, tag=m)

    s.udtf.register("blocks_of_page", Blocks)
    return s.sql("SELECT page_id, b.place, b.tag FROM {pages}, LATERAL blocks_of_page(html) b", pages=read(s, d, "pages").select("page_id", "html"))


# ---- functions of the chain by their SQL names


@operator(f"WITH {C.DETECTIONS_SQL}, p AS (SELECT a.key AS left_key, b.key AS right_key, greatest(0, least(a.x1, b.x1) - greatest(a.x0, b.x0)) * greatest(0, least(a.y1, b.y1) - greatest(a.y0, b.y0)) AS i, (a.x1 - a.x0) * (a.y1 - a.y0) + (b.x1 - b.x0) * (b.y1 - b.y0) AS u FROM detections a JOIN detections b ON a.volume_id = b.volume_id AND a.key < b.key) SELECT left_key, right_key, round(i / (u - i), 6)::DOUBLE AS overlap FROM p WHERE i / (u - i) > 0.2")
def op_box_overlap(s, d):
    box = F.struct("x0", "y0", "x1", "y1")
    rows = C.detections(s, d).select("volume_id", "key", box.alias("box"))
    a, b = rows.alias("a"), rows.alias("b")
    over = iou(F.col("a.box"), F.col("b.box"))
    return a.join(b, (F.col("a.volume_id") == F.col("b.volume_id")) & (F.col("a.key") < F.col("b.key"))).where(over > 0.2).select(F.col("a.key").alias("left_key"), F.col("b.key").alias("right_key"), F.round(over, 6).alias("overlap"))


@operator("SELECT a.vec_id, round(list_inner_product(a.embedding, b.embedding), 4)::DOUBLE AS score FROM embeddings a, (SELECT embedding FROM embeddings ORDER BY vec_id LIMIT 1) b")
def op_probe_scores(s, d):
    """Inner products with one stated probe row."""
    rows = read(s, d, "embeddings").select("vec_id", F.transform("embedding", lambda x: x.cast("double")).alias("v"))
    probe = rows.orderBy("vec_id").limit(1).select(F.col("v").alias("p"))
    return rows.crossJoin(F.broadcast(probe)).select("vec_id", F.round(dot(F.col("v"), F.col("p")), 4).alias("score"))


