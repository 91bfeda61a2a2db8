"""Assembling the released table, and studying it against its parent collection."""

from __future__ import annotations

from pyspark.sql import DataFrame, Window
from pyspark.sql import functions as F
from pyspark.sql import types as T

from ..config import CAPTION_FAILED, DEFAULT, PipelineConfig
from ..functions.expressions import linear_prob
from ..operators import collection, dedup, elements, fingerprints
from ..sources import carriers as C


def document_elements(spark, sf_dir: str) -> DataFrame:
    """Documents as crops: id, volume, language, text, detection confidence, class and its confidence."""
    docs = C.read(spark, sf_dir, "documents")
    u = C.unit_hash("doc_id", "class")
    raw = F.when(u < 0.68, "illustration").when(u < 0.78, "artifact").when(u < 0.86, "decorative").when(u < 0.93, "chart").otherwise("music")
    return docs.select(
        F.col("doc_id").alias("id"),
        F.col("source").alias("barcode_src"),
        F.col("lang").alias("language_src"),
        "text",
        (0.30 + 0.70 * C.unit_hash("doc_id", "det")).alias("detection_confidence"),
        raw.alias("raw_class"),
        F.sqrt(C.unit_hash("doc_id", "sure")).alias("class_confidence"),
    )


ELEMENTS_SQL = """u AS (SELECT doc_id, text, lang, source, ('0x' || substr(md5(doc_id || ':class'), 1, 8))::BIGINT / 4294967296.0::DOUBLE AS uc, ('0x' || substr(md5(doc_id || ':det'), 1, 8))::BIGINT / 4294967296.0::DOUBLE AS ud, ('0x' || substr(md5(doc_id || ':sure'), 1, 8))::BIGINT / 4294967296.0::DOUBLE AS us FROM documents),
elements AS (SELECT doc_id AS id, source AS barcode_src, lang AS language_src, text, 0.30::DOUBLE + 0.70::DOUBLE * ud AS detection_confidence,
CASE WHEN uc < 0.68 THEN 'illustration' WHEN uc < 0.78 THEN 'artifact' WHEN uc < 0.86 THEN 'decorative' WHEN uc < 0.93 THEN 'chart' ELSE 'music' END AS raw_class, sqrt(us) AS class_confidence FROM u)"""

MUSIC_TERMS = ["the", "und", "que", "les"]


def prepare(rows: DataFrame, groups: DataFrame, cfg: PipelineConfig = DEFAULT) -> DataFrame:
    """The released table: sure detections, unsure classes relabelled, one representative per group, provenance suffixes."""
    sure = rows.join(groups.select("id", "group_id"), "id").where(F.col("detection_confidence") >= cfg.keep_confidence)
    label = elements.relabel_other(F.col("raw_class"), F.col("class_confidence"), cfg.class_confidence)
    caption = elements.extractive_caption(F.col("text"), cfg.caption_words)
    guarded = elements.music_guard(label, F.col("class_confidence"), caption, MUSIC_TERMS, cfg.music_confidence)
    best = dedup.representatives(sure)
    final = sure.join(best.select("id"), "id", "left_semi")
    side = F.greatest(F.length("text"), F.lit(1))
    return final.select(
        "id",
        "barcode_src",
        F.length("text").alias("width_gen"),
        F.lit(48).alias("height_gen"),
        F.round(side * 48 / 1e6, 6).alias("pixel_count_mpx_gen"),
        F.round("detection_confidence", 6).alias("detection_confidence_gen"),
        guarded.alias("classification_gen"),
        F.round("class_confidence", 6).alias("classification_confidence_gen"),
        elements.finalize_caption(elements.caption_eligible(F.col("raw_class")), caption).alias("caption_exp"),
    )


# fixed values: names and types of the published record
FINAL_SCHEMA = """id bigint, crop_gen binary, barcode_src string, page_filename_src string, bbox_xyxy_gen array<float>, width_gen int, height_gen int,
pixel_count_mpx_gen double, detection_confidence_gen double, classification_gen string, classification_confidence_gen double,
classification_probs_gen array<struct<label:string,prob:double>>, phash_gen string, embedding_gen array<double>, caption_exp string,
caption_linear_prob_exp double, caption_lang_passed_exp string, caption_lang_detected_exp string,
caption_thesauri_matches_exp map<string,map<string,int>>, orientation_correction_gen string, orientation_correction_confidence_gen double,
orientation_correction_probs_gen array<struct<label:string,prob:double>>"""
# fixed values: the corrections, by quarter turns
CORRECTIONS = ("upright", "rotate_90_clockwise", "rotate_180", "rotate_90_counterclockwise")


def release_record(spark, sf_dir: str, released: DataFrame, prints: DataFrame, cfg: PipelineConfig = DEFAULT) -> DataFrame:
    """The released elements as the published record of 22 columns. ``prints`` has (id, hash, packed). A document has no
    picture, so ``crop_gen`` is null; what a step did not produce for an element is null too."""
    docs = C.read(spark, sf_dir, "documents").select(F.col("doc_id").alias("id"), "lang", "text")
    rows = released.join(docs, "id").join(prints.select("id", F.col("hash").alias("phash_gen"), "packed"), "id", "left").withColumn("embedding_gen", fingerprints.unpacked(F.col("packed")))
    turned = elements.orientation_scores(rows.withColumn("degrees", F.lit(0)))
    labels = F.array(*[F.lit(x) for x in CORRECTIONS])
    probs = F.array_sort(F.transform("scores", lambda p, k: F.struct(F.get(labels, k).alias("label"), p.alias("prob"))), lambda a, b: F.when(a["prob"] > b["prob"], -1).when(a["prob"] < b["prob"], 1).when(a["label"] < b["label"], -1).otherwise(1))
    pictured = F.col("classification_gen").isin("illustration", "chart")
    best = F.get(probs, 0)
    said = F.when(best["prob"] >= cfg.orient_confidence, best["label"]).otherwise(CORRECTIONS[0])
    words = F.filter(F.split(F.coalesce("caption_exp", F.lit("")), r"\s+"), lambda w: w != "")
    # the built-in provider is sure of short words; it stands for stored token log-probabilities
    tokens = F.transform(words, lambda w: -F.length(w) / F.lit(100.0))
    hits = F.map_from_entries(F.transform(F.array(*[F.lit(t) for t in MUSIC_TERMS]), lambda t: F.struct(t, F.map_from_arrays(F.array(t), F.array(F.size(F.filter(words, lambda w: w == t)))))))
    code = F.coalesce(F.try_element_at(F.create_map(*[F.lit(x) for k, v in {"en": "eng", "de": "deu", "fr": "fra", "es": "spa"}.items() for x in (k, v)]), F.col("lang")), F.lit("eng"))
    probs_of_class = collection.softmax([C.unit_hash("id", f"p{k}") for k in range(5)])
    captioned = F.col("caption_exp").isNotNull()
    columns = {
        "crop_gen": F.lit(None),
        "page_filename_src": F.concat("barcode_src", F.lit("/"), F.col("id").cast("string"), F.lit(".txt")),
        "bbox_xyxy_gen": F.array(F.lit(0.0), F.lit(0.0), F.col("width_gen").cast("double"), F.col("height_gen").cast("double")),
        "classification_probs_gen": probs_of_class,
        "caption_linear_prob_exp": F.when(captioned, linear_prob(tokens)),
        "caption_lang_passed_exp": F.when(captioned, code),
        "caption_lang_detected_exp": F.when(captioned & (F.col("caption_exp") != CAPTION_FAILED), code),
        "caption_thesauri_matches_exp": F.when(captioned, F.map_filter(hits, lambda k, v: F.element_at(F.map_values(v), 1) > 0)),
        "orientation_correction_gen": F.when(pictured, said),
        "orientation_correction_confidence_gen": F.when(pictured, best["prob"]),
        "orientation_correction_probs_gen": F.when(pictured, probs),
    }
    schema = T.StructType.fromDDL(FINAL_SCHEMA)
    return turned.select(*[columns.get(f.name, F.col(f.name) if f.name in turned.columns else F.lit(None)).cast(f.dataType).alias(f.name) for f in schema.fields])


def check_suffixes(df: DataFrame, keys=("id",)) -> list[str]:
    """Columns that break the provenance contract (_src, _gen or _exp)."""
    return [c for c in df.columns if c not in keys and not c.endswith(("_src", "_gen", "_exp"))]


def release_groups(prints: DataFrame, cfg: PipelineConfig = DEFAULT) -> DataFrame:
    """(id, group_id) from (id, hash) and vec or packed: elements are one group only where the bit hash and the vector both put them
    together."""
    by_hash = dedup.hash_groups(prints.select("id", "hash"), cfg.hamming, cfg.bands, cfg.band_bits)
    by_vector = dedup.vector_groups(prints.drop("hash"), cfg.similarity)
    return dedup.intersect_groups(by_hash, by_vector).select("id", "group_id")


def released(spark, sf_dir: str) -> tuple[DataFrame, DataFrame]:
    """The release's own columns, and the fingerprints they were grouped by, which are worked out once and kept."""
    rows = document_elements(spark, sf_dir)
    prints = fingerprints.kept(fingerprints.packed(fingerprints.fingerprint(rows)))
    return prepare(rows, release_groups(prints)), prints


def flagship(spark, sf_dir: str) -> DataFrame:
    return released(spark, sf_dir)[0]


def full_record(spark, sf_dir: str) -> DataFrame:
    return release_record(spark, sf_dir, *released(spark, sf_dir))


# ---- workloads over detections and volumes


def per_volume(spark, sf_dir: str) -> DataFrame:
    counts = C.detections(spark, sf_dir).groupBy("volume_id").agg(F.count("*").alias("n"))
    per = C.volumes(spark, sf_dir).select("volume_id").join(counts, "volume_id", "left").select(F.coalesce("n", F.lit(0)).alias("n"))
    some = F.when(F.col("n") > 0, F.col("n"))
    return per.agg(F.count("*").alias("volumes"), F.count_if(F.col("n") == 0).alias("empty"), F.round(F.avg("n"), 6).alias("mean_all"), F.round(F.avg(some), 6).alias("mean_non_empty"), F.percentile("n", F.lit(0.5)).alias("median"), F.max("n").alias("largest"))


def histogram(spark, sf_dir: str, log: bool = False) -> DataFrame:
    counts = C.detections(spark, sf_dir).groupBy("volume_id").agg(F.count("*").alias("n"))
    bin_ = F.floor(F.log2("n")).cast("int") if log else F.col("n").cast("int")
    return counts.groupBy(bin_.alias("bin")).agg(F.count("*").alias("volumes"))


def funnel(spark, sf_dir: str) -> DataFrame:
    d = C.detections(spark, sf_dir)
    return d.agg(
        F.count("*").alias("raw"),
        F.count_if(F.col("detection_confidence") >= DEFAULT.keep_confidence).alias("sure"),
        F.count_if((F.col("detection_confidence") >= DEFAULT.keep_confidence) & (F.col("class_confidence") >= DEFAULT.class_confidence)).alias("sure_and_classed"),
        F.count_distinct("volume_id").alias("volumes_with"),
        F.count_distinct(F.when(F.col("detection_confidence") >= DEFAULT.keep_confidence, F.col("volume_id"))).alias("volumes_sure"),
    )


def box_profile(spark, sf_dir: str) -> DataFrame:
    d = C.detections(spark, sf_dir).select((F.col("x1") - F.col("x0")).alias("w"), (F.col("y1") - F.col("y0")).alias("h"))
    out = []
    for c in ("w", "h"):
        out += [F.min(c).cast("bigint").alias(f"{c}_min"), F.max(c).cast("bigint").alias(f"{c}_max"), F.round(F.avg(c), 6).alias(f"{c}_mean"), F.percentile(c, F.lit(0.5)).alias(f"{c}_median")]
    return d.agg(*out)


def class_share(spark, sf_dir: str) -> DataFrame:
    g = C.detections(spark, sf_dir).groupBy("raw_class").agg(F.count("*").alias("n"))
    return g.select("raw_class", "n", F.round(F.col("n") / F.sum("n").over(Window.partitionBy()), 6).alias("share"))


def relabel_shift(spark, sf_dir: str) -> DataFrame:
    """Per class: count before and after, and the share moved to other."""
    d = C.detections(spark, sf_dir).withColumn("after", elements.relabel_other(F.col("raw_class"), F.col("class_confidence"), DEFAULT.class_confidence))
    before = d.groupBy(F.col("raw_class").alias("label")).agg(F.count("*").alias("n_before"), F.count_if(F.col("after") == "other").alias("moved"))
    after = d.groupBy(F.col("after").alias("label")).agg(F.count("*").alias("n_after"))
    j = before.join(after, "label", "full_outer")
    return j.select("label", F.coalesce("n_before", F.lit(0)).alias("n_before"), F.coalesce("n_after", F.lit(0)).alias("n_after"), F.round(F.coalesce(F.col("moved") / F.col("n_before"), F.lit(0.0)), 6).alias("moved_share"))


def confidence_profile(spark, sf_dir: str) -> DataFrame:
    d = C.detections(spark, sf_dir)
    c = F.col("class_confidence")
    return d.groupBy("raw_class").agg(F.count("*").alias("n"), F.round(F.avg(c), 6).alias("mean"), F.round(F.percentile(c, F.lit(0.5)), 6).alias("median"), F.round(F.avg((c >= 0.95).cast("int")), 6).alias("share_sure"), F.round(F.avg((c < 0.5).cast("int")), 6).alias("share_low"))


def temporal_coverage(spark, sf_dir: str, least: int = DEFAULT.coverage_minimum) -> DataFrame:
    """Volumes by year with the second date as fallback: all of them and those with enough detections."""
    d = C.detections(spark, sf_dir).groupBy("volume_id").agg(F.count("*").alias("n"), F.year(F.min("shipped")).alias("date2"))
    v = C.volumes(spark, sf_dir).join(d, "volume_id", "left").withColumn("year", F.coalesce("date1_src", "date2")).where("year IS NOT NULL")
    return v.groupBy("year").agg(F.count("*").alias("volumes"), F.count_if(F.col("n") >= least).alias("visual"))


def coverage_by(spark, sf_dir: str, by: str, top: int = 20, least: int = DEFAULT.coverage_minimum) -> DataFrame:
    """Volumes, detections and shares by language or topic; the ``top`` largest."""
    d = C.detections(spark, sf_dir).groupBy("volume_id").agg(F.count("*").alias("n"))
    v = C.volumes(spark, sf_dir).join(d, "volume_id", "left")
    g = v.groupBy(by).agg(F.count("*").alias("volumes"), F.coalesce(F.sum("n"), F.lit(0)).alias("detections"), F.count_if(F.col("n") >= least).alias("visual"))
    all_ = Window.partitionBy()
    out = g.select(by, "volumes", "detections", "visual", F.round(F.col("detections") / F.sum("detections").over(all_), 6).alias("share_detections"), F.round(F.col("volumes") / F.sum("volumes").over(all_), 6).alias("share_volumes"), F.round(F.col("visual") / F.col("volumes"), 6).alias("reach"))
    return out.orderBy(F.desc("detections"), by).limit(top)


def reach_cube(spark, sf_dir: str, least: int = DEFAULT.coverage_minimum) -> DataFrame:
    d = C.detections(spark, sf_dir).groupBy("volume_id").agg(F.count("*").alias("n"))
    v = C.volumes(spark, sf_dir).join(d, "volume_id", "left").withColumn("hit", F.coalesce(F.col("n") >= least, F.lit(False)).cast("int"))
    return v.cube("language_src", "topic").agg(F.count("*").alias("volumes"), F.round(F.avg("hit"), 6).alias("reach"))


def concentration(spark, sf_dir: str) -> DataFrame:
    """Share of detections that the tenth of the volumes with most of them holds, by topic.

    Volumes are counted by size first, so the window runs over the distinct sizes of a topic and not over its volumes;
    the size at which the tenth ends counts with the part of its volumes that is inside.
    """
    d = C.detections(spark, sf_dir).groupBy("volume_id").agg(F.count("*").alias("n"))
    sizes = C.volumes(spark, sf_dir).join(d, "volume_id").groupBy("topic", "n").agg(F.count("*").alias("volumes"))
    larger = Window.partitionBy("topic").orderBy(F.desc("n")).rowsBetween(Window.unboundedPreceding, -1)
    all_ = Window.partitionBy("topic")
    r = sizes.withColumn("before", F.coalesce(F.sum("volumes").over(larger), F.lit(0))).withColumn("tenth", F.ceil(F.sum("volumes").over(all_) / 10))
    inside = F.greatest(F.lit(0), F.least("volumes", F.col("tenth") - F.col("before")))
    return r.groupBy("topic").agg(F.round(F.sum(inside * F.col("n")) / F.sum(F.col("volumes") * F.col("n")), 6).alias("top_share"))


# ---- footprint


def step_shares(spark, sf_dir: str) -> DataFrame:
    """Time per step over the whole span and over active time (``error`` plays downtime)."""
    g = C.run_log(spark, sf_dir).groupBy("step").agg(F.sum("seconds").alias("s"), F.count("*").alias("items"))
    all_ = Window.partitionBy()
    active = F.when(F.col("step") != "error", F.col("s"))
    return g.select("step", "items", F.round("s", 4).alias("seconds"), F.round(F.col("s") / F.sum("s").over(all_), 6).alias("share_span"), F.round(active / F.sum(active).over(all_), 6).alias("share_active"))


def batch_profile(spark, sf_dir: str) -> DataFrame:
    g = C.run_log(spark, sf_dir).groupBy("step", "batch").agg(F.sum("seconds").alias("s"))
    return g.groupBy("step").agg(F.count("*").alias("batches"), F.round(F.avg("s"), 4).alias("mean"), F.round(F.min("s"), 4).alias("least"), F.round(F.max("s"), 4).alias("most"))


def drift(spark, sf_dir: str) -> DataFrame:
    g = C.run_log(spark, sf_dir).groupBy("step", "batch").agg(F.sum("seconds").alias("s"))
    return g.groupBy("step").agg(F.round(F.regr_slope("s", "batch"), 4).alias("slope"))


def plan_batches(volumes: DataFrame, size: int = DEFAULT.volumes_per_batch) -> DataFrame:
    """(batch, volumes): at most ``size`` volumes a batch, dealt by a hash of the id so that no global order is needed."""
    n = volumes.count()
    batches = max(1, -(-n // max(1, size * 9 // 10)))
    return volumes.withColumn("batch", F.pmod(F.xxhash64("volume_id"), F.lit(batches)))


def api_cost(spark, sf_dir: str, price_per_million: float = 0.075, cached_share: float = 0.25) -> DataFrame:
    calls = C.caption_calls(spark, sf_dir)
    tokens = F.size(F.filter(F.split(F.coalesce("request", F.lit("")), r"\s+"), lambda w: w != ""))
    return calls.agg(F.count("*").alias("requests"), F.count("response").alias("answered"), F.sum(tokens).cast("bigint").alias("input_tokens"), F.round(F.sum(tokens) * price_per_million * (1 - cached_share / 2) / 1e6, 9).alias("cost"))
