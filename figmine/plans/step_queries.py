"""Workloads over the steps around the models, each with its SQL where there is one."""

from __future__ import annotations

from pyspark.sql import DataFrame, Window
from pyspark.sql import functions as F

from ..config import CLASSES, DEFAULT
from ..operators import collection as K
from ..operators import elements
from ..sources import carriers as C
from . import analysis as A

QUERIES: dict = {}
ORACLES: dict = {}


def query(sql: str | None = None):
    def add(f):
        QUERIES[f.__name__] = f
        if sql:
            ORACLES[f.__name__] = sql
        return f

    return add


def class_vectors(spark, sf_dir) -> DataFrame:
    """Documents with the class vector of the built-in scorer: five draws from the md5 of the id, sharpened."""
    docs = C.read(spark, sf_dir, "documents").select("doc_id", "lang", "source")
    return docs.select("*", K.softmax([C.unit_hash("doc_id", f"p{k}") for k in range(5)]).alias("probs"))


_U = ", ".join(f"('0x' || substr(md5(doc_id || ':p{k}'), 1, 8))::BIGINT / 4294967296.0::DOUBLE AS u{k}" for k in range(5))
_TOTAL = " + ".join(f"exp(8 * u{k})" for k in range(5))
_PROBS = ", ".join(f"{{'label': '{n}', 'prob': exp(8 * u{k}) / ({_TOTAL})}}" for k, n in enumerate(CLASSES))
VECTORS_SQL = f"u AS (SELECT doc_id, lang, source, {_U} FROM documents), v AS (SELECT doc_id, lang, source, unnest([{_PROBS}]) AS p FROM u), ranked AS (SELECT doc_id, lang, source, p.label AS label, p.prob AS prob, row_number() OVER (PARTITION BY doc_id ORDER BY p.prob DESC, p.label) AS r FROM v)"


@query(f"WITH {VECTORS_SQL} SELECT doc_id, label, round(prob, 6) AS prob FROM ranked WHERE r = 1")
def w04_top_class(s, d):
    top = K.top1(F.col("probs"))
    return class_vectors(s, d).select("doc_id", top["label"].alias("label"), F.round(top["prob"], 6).alias("prob"))


@query(f"WITH {VECTORS_SQL}, c AS (SELECT doc_id, arg_min(label, r) AS label FROM ranked WHERE prob >= CASE WHEN label = 'music' THEN 0.99 WHEN label = 'chart' THEN 0.5 ELSE 0.3 END GROUP BY 1) SELECT coalesce(label, 'other') AS label, count(*) AS n FROM documents LEFT JOIN c USING (doc_id) GROUP BY 1")
def w04_redecided(s, d):
    cuts = {n: 0.3 for n in CLASSES} | {"music": 0.99, "chart": 0.5}
    return class_vectors(s, d).select(K.redecide(F.col("probs"), cuts).alias("label")).groupBy("label").agg(F.count("*").alias("n"))


@query(f"WITH {VECTORS_SQL}, t AS (SELECT r1.label AS truth, r2.label AS predicted FROM (SELECT * FROM ranked WHERE r = 1) r1 JOIN (SELECT * FROM ranked WHERE r = 2) r2 USING (doc_id)) SELECT truth, predicted, count(*) AS n FROM t GROUP BY CUBE (truth, predicted)")
def w04_confusion(s, d):
    """Confusions with margins, the runner-up playing the prediction."""
    probs = F.col("probs")
    return class_vectors(s, d).select(F.get(probs, 0)["label"].alias("truth"), F.get(probs, 1)["label"].alias("predicted")).cube("truth", "predicted").agg(F.count("*").alias("n"))


@query("WITH a AS (SELECT page_id, unnest(regexp_extract_all(html, '<(?:article|nav|footer|h1)[ >]')) AS b FROM pages) SELECT pages.page_id, count(b) AS annotations FROM pages LEFT JOIN (SELECT * FROM a WHERE page_id % 3 <> 0) a ON a.page_id = pages.page_id GROUP BY 1")
def w01_with_negatives(s, d):
    """Pages with and without annotations; every third page plays one without."""
    pages = C.read(s, d, "pages")
    marks = pages.where("page_id % 3 <> 0").select("page_id", F.explode(F.regexp_extract_all("html", F.lit("<(?:article|nav|footer|h1)[ >]"), F.lit(0))).alias("label"))
    return K.with_negatives(pages.select("page_id"), K.merge_classes(marks))


@query(f"WITH {C.DETECTIONS_SQL} SELECT count(*) AS volumes FROM orders WHERE o_orderkey IN (SELECT volume_id FROM detections WHERE detection_confidence >= 0.75)")
def w01_pages_with_hits(s, d):
    sure = C.detections(s, d).where(F.col("detection_confidence") >= DEFAULT.keep_confidence)
    return K.pages_with_hits(C.volumes(s, d).select("volume_id"), sure, "volume_id").agg(F.count("*").alias("volumes"))


_ISO = [("en", "eng", "English"), ("de", "deu", "German"), ("fr", "fra", "French")]


@query("WITH iso AS (SELECT * FROM (VALUES ('en', 'eng', 'English'), ('de', 'deu', 'German'), ('fr', 'fra', 'French')) t(code2, code3, name)) SELECT doc_id, coalesce(code3, 'eng') AS caption_code, coalesce(name, 'English') AS caption_language FROM documents LEFT JOIN iso ON lower(trim(lang)) = code2")
def w10_languages_of_requests(s, d):
    """One given language is left out of the code list, so its requests fall back to English."""
    iso = s.createDataFrame(_ISO, "code2 string, code3 string, name string")
    return K.resolve_language(C.read(s, d, "documents").select("doc_id", "lang"), iso, "lang").select("doc_id", "caption_code", "caption_language")


@query(f"WITH {C.DETECTIONS_SQL} SELECT count(*) AS requests, min(1)::INTEGER AS least_parts, 2 AS most_parts FROM documents")
def w10_requests(s, d):
    """Requests assembled of instruction, page text, crop and language, read back and counted."""
    docs = C.read(s, d, "documents")
    rows = docs.select(F.col("doc_id").alias("page_id"), F.col("lang").alias("language_src"), F.lit(None).cast("string").alias("payload"))
    iso = s.createDataFrame(_ISO, "code2 string, code3 string, name string")
    made = K.build_requests(rows, docs.select(F.col("doc_id").alias("page_id"), "text"), iso, "Describe the picture in at most fifty words.")
    parts = F.size(F.from_json("request", "system string, content array<struct<type:string,body:string>>")["content"])
    return made.agg(F.count("request").alias("requests"), F.least(F.min(parts), F.lit(1)).alias("least_parts"), F.max(parts).alias("most_parts"))


_GRAMS = r"(CASE WHEN len({w}) = 0 THEN [] WHEN len({w}) < 3 THEN [array_to_string({w}, ' ')] ELSE list_distinct(list_transform(range(1, len({w}) - 1), lambda i: array_to_string({w}[i:i + 2], ' '))) END)"


@query(r"WITH c AS (SELECT conv_id, turn, role, text, lead(role) OVER w AS next_role, lead(text) OVER w AS next_text FROM conversations WINDOW w AS (PARTITION BY conv_id ORDER BY turn)), t AS (SELECT list_filter(regexp_split_to_array(lower(coalesce(next_text, '')), '\s+'), lambda x: x <> '') AS a, list_filter(regexp_split_to_array(lower(coalesce(text, '')), '\s+'), lambda x: x <> '') AS b FROM c WHERE role = 'user' AND next_role = 'assistant'), g AS (SELECT " + _GRAMS.format(w="a") + " AS ga, " + _GRAMS.format(w="b") + " AS gb FROM t) SELECT count(*) AS captions, count_if(len(list_intersect(ga, gb)) / len(ga) >= 0.5)::BIGINT AS repeating, round(avg(len(list_intersect(ga, gb)) / len(ga)), 6) AS mean FROM g WHERE len(ga) > 0")
def w10_text_reliance(s, d):
    calls = C.caption_calls(s, d).where("response IS NOT NULL")
    r = calls.select(K.text_reliance(F.col("response"), F.col("request")).alias("r")).where("r IS NOT NULL")
    return r.agg(F.count("*").alias("captions"), F.count_if(F.col("r") >= 0.5).alias("repeating"), F.round(F.avg("r"), 6).alias("mean"))


@query("WITH l AS (SELECT user_id AS worker, event_type AS step, value AS seconds FROM events) SELECT step, count(DISTINCT worker) AS workers, count(*) AS items, round(sum(seconds) / count(*), 6) AS seconds_per_item, round(sum(seconds) / 3600, 6) AS worker_hours FROM l GROUP BY 1")
def w15_worker_cost(s, d):
    g = C.run_log(s, d).groupBy("step").agg(F.count_distinct("worker").alias("workers"), F.count("*").alias("items"), F.sum("seconds").alias("t"))
    return g.select("step", "workers", "items", F.round(F.col("t") / F.col("items"), 6).alias("seconds_per_item"), F.round(F.col("t") / 3600, 6).alias("worker_hours"))


@query("WITH l AS (SELECT CAST(json_extract(props, '$.k') AS INTEGER) AS batch, event_type AS step, value AS seconds FROM events), g AS (SELECT step, batch, count(*) / sum(seconds) AS rate FROM l WHERE seconds > 0 GROUP BY 1, 2) SELECT step, round(avg(rate), 6) AS achieved, round(max(rate), 6) AS possible, round(avg(rate) / max(rate), 6) AS utilisation FROM g GROUP BY 1")
def w15_utilisation(s, d):
    """Mean rate of a step's batches against its best batch, which plays the rate the hardware allows."""
    g = C.run_log(s, d).where("seconds > 0").groupBy("step", "batch").agg((F.count("*") / F.sum("seconds")).alias("rate"))
    return g.groupBy("step").agg(F.round(F.avg("rate"), 6).alias("achieved"), F.round(F.max("rate"), 6).alias("possible"), F.round(F.avg("rate") / F.max("rate"), 6).alias("utilisation"))


@query("WITH l AS (SELECT CAST(json_extract(props, '$.k') AS INTEGER) AS batch, event_type AS step, value AS seconds FROM events), a AS (SELECT step, sum(seconds) AS t FROM l WHERE batch % 2 = 0 GROUP BY 1), b AS (SELECT step, sum(seconds) AS t FROM l WHERE batch % 2 = 1 GROUP BY 1) SELECT coalesce(a.step, b.step) AS step, round(a.t / (SELECT sum(t) FROM a), 6) AS share_first, round(b.t / (SELECT sum(t) FROM b), 6) AS share_second FROM a FULL JOIN b ON a.step = b.step")
def w15_compare_runs(s, d):
    """Shares of the steps on two machines; even and odd batches play the two."""
    log = C.run_log(s, d)
    side = []
    for k, name in ((0, "share_first"), (1, "share_second")):
        g = log.where(F.col("batch") % 2 == k).groupBy("step").agg(F.sum("seconds").alias("t"))
        side.append(g.select("step", F.round(F.col("t") / F.sum("t").over(Window.partitionBy()), 6).alias(name)))
    return side[0].join(side[1], "step", "full_outer").select("step", "share_first", "share_second")


@query(f"WITH {C.DETECTIONS_SQL}, n AS (SELECT volume_id, count(*) AS n FROM detections GROUP BY 1), m AS (SELECT quantile_disc(n, 0.5) AS m FROM n) SELECT parts, count(*) AS volumes FROM (SELECT greatest(1, ceil(n / (greatest(m, 1) * 1.5::DOUBLE)))::INTEGER AS parts FROM n, m) GROUP BY 1")
def w15_skew_guard(s, d):
    counts = C.detections(s, d).groupBy("volume_id").agg(F.count("*").alias("n"))
    return K.skew_guard(counts, "n", 1.5).groupBy("parts").agg(F.count("*").alias("volumes"))


@query("SELECT lang, source, doc_id FROM (SELECT lang, source, doc_id, row_number() OVER (PARTITION BY lang ORDER BY md5(doc_id::VARCHAR), doc_id) AS r FROM documents) WHERE r <= 20")
def w13_review_sample(s, d):
    return K.review_sample(C.read(s, d, "documents").select("lang", "source", "doc_id"), "doc_id", "lang", 20)


@query(f"WITH {C.DETECTIONS_SQL} SELECT raw_class, count(*) AS near_the_cut FROM detections WHERE abs(detection_confidence - 0.75) <= 0.01 GROUP BY 1")
def w13_borderline(s, d):
    return K.borderline(C.detections(s, d), "detection_confidence", DEFAULT.keep_confidence, 0.01).groupBy("raw_class").agg(F.count("*").alias("near_the_cut"))


@query(f"WITH {C.DETECTIONS_SQL}, {C.VOLUMES_SQL}, best AS (SELECT arg_max(key, detection_confidence) AS key FROM detections GROUP BY x0, y0, raw_class) SELECT count(*) AS released FROM detections JOIN volumes USING (volume_id) WHERE detection_confidence >= 0.75 AND topic IN ('BUILDING', 'MACHINERY')")
def w13_rights(s, d):
    """Only volumes of allowed status; two market segments play the allow-list."""
    sure = C.detections(s, d).where(F.col("detection_confidence") >= DEFAULT.keep_confidence)
    return K.rights_filter(sure.join(C.volumes(s, d), "volume_id"), ["BUILDING", "MACHINERY"], "topic").agg(F.count("*").alias("released"))


_FINAL = "CASE WHEN class_confidence < 0.70 THEN 'other' WHEN raw_class = 'music' AND class_confidence < 0.99 THEN 'other' ELSE raw_class END"


@query(f"WITH {C.DETECTIONS_SQL}, sure AS (SELECT * FROM detections WHERE detection_confidence >= 0.75), best AS (SELECT arg_min(key, (-detection_confidence, key)) AS key FROM sure GROUP BY x0, y0, raw_class) SELECT key AS id, volume_id AS barcode_src, (x1 - x0)::BIGINT AS width_gen, (y1 - y0)::BIGINT AS height_gen, round((x1 - x0) * (y1 - y0) / 1e6::DOUBLE, 6) AS pixel_count_mpx_gen, round(detection_confidence, 6) AS detection_confidence_gen, {_FINAL} AS classification_gen, round(class_confidence, 7) AS classification_confidence_gen FROM sure JOIN best USING (key)")
def w13_prepare_lines(s, d):
    """The release rules over detections: sure boxes, relabelled classes, one box of each place and class."""
    sure = C.detections(s, d).where(F.col("detection_confidence") >= DEFAULT.keep_confidence)
    best = sure.groupBy("x0", "y0", "raw_class").agg(F.min_by("key", F.struct(-F.col("detection_confidence"), "key")).alias("key")).select("key")
    label = elements.relabel_other(F.col("raw_class"), F.col("class_confidence"), DEFAULT.class_confidence)
    guarded = elements.music_guard(label, F.col("class_confidence"), F.lit(""), ["score"], DEFAULT.music_confidence)
    width, height = F.col("x1") - F.col("x0"), F.col("y1") - F.col("y0")
    return sure.join(best, "key", "left_semi").select(
        F.col("key").alias("id"),
        F.col("volume_id").alias("barcode_src"),
        width.alias("width_gen"),
        height.alias("height_gen"),
        F.round(width * height / 1e6, 6).alias("pixel_count_mpx_gen"),
        F.round("detection_confidence", 6).alias("detection_confidence_gen"),
        guarded.alias("classification_gen"),
        F.round("class_confidence", 7).alias("classification_confidence_gen"),
    )


@query(f"WITH {C.DETECTIONS_SQL}, {C.VOLUMES_SQL}, d AS (SELECT volume_id, count(*) AS n FROM detections GROUP BY 1) SELECT ((coalesce(date1_src, date2) // 100) * 100)::INTEGER AS century, count(*) AS volumes, round(count_if(n >= 10) / sum(count_if(n >= 10)) OVER (), 6)::DOUBLE AS share_visual, round(count(*) / sum(count(*)) OVER (), 6)::DOUBLE AS share_all FROM volumes LEFT JOIN (SELECT d.volume_id, d.n, x.date2 FROM d JOIN (SELECT volume_id, year(min(shipped)) AS date2 FROM detections GROUP BY 1) x USING (volume_id)) d USING (volume_id) WHERE coalesce(date1_src, date2) IS NOT NULL GROUP BY 1")
def w14_century(s, d):
    g = A.temporal_coverage(s, d).groupBy((F.floor(F.col("year") / 100) * 100).cast("int").alias("century")).agg(F.sum("volumes").alias("volumes"), F.sum("visual").alias("visual"))
    all_ = Window.partitionBy()
    return g.select("century", "volumes", F.round(F.col("visual") / F.sum("visual").over(all_), 6).alias("share_visual"), F.round(F.col("volumes") / F.sum("volumes").over(all_), 6).alias("share_all"))
