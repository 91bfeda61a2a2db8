"""Queries of the chain's workloads over the given tables, with their SQL where it exists."""

from __future__ import annotations

import zlib
from collections import Counter
from functools import partial

import numpy as np
import pyarrow as pa
from pyspark.sql import Window
from pyspark.sql import functions as F

from ..functions.expressions import cosine, linear_prob, mean_logprob
from ..operators import collection, dedup, elements, fingerprints, knn, sweeps
from ..sources import carriers as C
from . import analysis as A

QUERIES: dict = {}
ORACLES: dict = {}


def _add(name, query, sql=None):
    QUERIES[name] = query
    if sql:
        ORACLES[name] = sql


DV = f"WITH {C.DETECTIONS_SQL}, {C.VOLUMES_SQL}"
_add("w02_funnel", A.funnel, f"WITH {C.DETECTIONS_SQL} SELECT count(*) AS raw, count_if(detection_confidence >= 0.75)::BIGINT AS sure, count_if(detection_confidence >= 0.75 AND class_confidence >= 0.70)::BIGINT AS sure_and_classed, count(DISTINCT volume_id) AS volumes_with, count(DISTINCT CASE WHEN detection_confidence >= 0.75 THEN volume_id END) AS volumes_sure FROM detections")
_add("w02_per_volume", A.per_volume, f"{DV}, p AS (SELECT coalesce(c.n, 0) AS n FROM volumes LEFT JOIN (SELECT volume_id, count(*) AS n FROM detections GROUP BY 1) c USING (volume_id)) SELECT count(*) AS volumes, count_if(n = 0)::BIGINT AS empty, round(avg(n), 6) AS mean_all, round(avg(CASE WHEN n > 0 THEN n END), 6) AS mean_non_empty, quantile_cont(n, 0.5) AS median, max(n) AS largest FROM p")
_add("w02_hist_linear", A.histogram, f"WITH {C.DETECTIONS_SQL} SELECT n::INTEGER AS bin, count(*) AS volumes FROM (SELECT volume_id, count(*) AS n FROM detections GROUP BY 1) GROUP BY 1")
_add("w02_hist_log", partial(A.histogram, log=True), f"WITH {C.DETECTIONS_SQL} SELECT floor(log2(n))::INTEGER AS bin, count(*) AS volumes FROM (SELECT volume_id, count(*) AS n FROM detections GROUP BY 1) GROUP BY 1")
_box = ", ".join(f"min({e})::BIGINT AS {c}_min, max({e})::BIGINT AS {c}_max, round(avg({e}), 6) AS {c}_mean, quantile_cont({e}, 0.5)::DOUBLE AS {c}_median" for c, e in (("w", "(x1 - x0)"), ("h", "(y1 - y0)")))
_add("w03_box_profile", A.box_profile, f"WITH {C.DETECTIONS_SQL} SELECT {_box} FROM detections")
_add("w05_class_share", A.class_share, f"WITH {C.DETECTIONS_SQL} SELECT raw_class, count(*) AS n, round(count(*) / sum(count(*)) OVER (), 6)::DOUBLE AS share FROM detections GROUP BY 1")
_add("w05_relabel_shift", A.relabel_shift, f"WITH {C.DETECTIONS_SQL}, d AS (SELECT raw_class, CASE WHEN class_confidence < 0.70 THEN 'other' ELSE raw_class END AS after FROM detections), b AS (SELECT raw_class AS label, count(*) AS n, count_if(after = 'other') AS m FROM d GROUP BY 1), a AS (SELECT after AS label, count(*) AS n FROM d GROUP BY 1) SELECT coalesce(b.label, a.label) AS label, coalesce(b.n, 0) AS n_before, coalesce(a.n, 0) AS n_after, round(coalesce(b.m / b.n, 0.0), 6)::DOUBLE AS moved_share FROM b FULL JOIN a ON a.label = b.label")
_add("w05_confidence", A.confidence_profile, f"WITH {C.DETECTIONS_SQL} SELECT raw_class, count(*) AS n, round(avg(class_confidence), 6) AS mean, round(quantile_cont(class_confidence, 0.5), 6) AS median, round(avg((class_confidence >= 0.95)::INT), 6) AS share_sure, round(avg((class_confidence < 0.5)::INT), 6) AS share_low FROM detections GROUP BY 1")
_add("w14_temporal", A.temporal_coverage, f"{DV}, d AS (SELECT volume_id, count(*) AS n, year(min(shipped)) AS date2 FROM detections GROUP BY 1) SELECT coalesce(date1_src, date2)::INTEGER AS year, count(*) AS volumes, count_if(n >= 10)::BIGINT AS visual FROM volumes LEFT JOIN d USING (volume_id) WHERE coalesce(date1_src, date2) IS NOT NULL GROUP BY 1")
for _name, _by in (("w14_language", "language_src"), ("w14_topic", "topic")):
    _add(_name, partial(A.coverage_by, by=_by), f"{DV}, d AS (SELECT volume_id, count(*) AS n FROM detections GROUP BY 1), g AS (SELECT {_by}, count(*) AS volumes, coalesce(sum(n), 0)::BIGINT AS detections, count_if(n >= 10)::BIGINT AS visual FROM volumes LEFT JOIN d USING (volume_id) GROUP BY 1) SELECT {_by}, volumes, detections, visual, round(detections / sum(detections) OVER (), 6)::DOUBLE AS share_detections, round(volumes / sum(volumes) OVER (), 6)::DOUBLE AS share_volumes, round(visual / volumes, 6)::DOUBLE AS reach FROM g ORDER BY detections DESC, {_by} LIMIT 20")
_add("w14_reach", A.reach_cube, f"{DV}, d AS (SELECT volume_id, count(*) AS n FROM detections GROUP BY 1) SELECT language_src, topic, count(*) AS volumes, round(avg(coalesce(n >= 10, false)::INT), 6) AS reach FROM volumes LEFT JOIN d USING (volume_id) GROUP BY CUBE (language_src, topic)")
_add("w14_concentration", A.concentration, f"{DV}, d AS (SELECT volume_id, count(*) AS n FROM detections GROUP BY 1), r AS (SELECT topic, n, row_number() OVER (PARTITION BY topic ORDER BY n DESC) AS r, count(*) OVER (PARTITION BY topic) AS k FROM volumes JOIN d USING (volume_id)) SELECT topic, round(sum(CASE WHEN r <= ceil(k / 10) THEN n ELSE 0 END) / sum(n), 6)::DOUBLE AS top_share FROM r GROUP BY 1")
_LOG = "l AS (SELECT CAST(json_extract(props, '$.k') AS INTEGER) AS batch, event_type AS step, value AS seconds FROM events)"
_add("w15_step_shares", A.step_shares, f"WITH {_LOG}, g AS (SELECT step, sum(seconds) AS s, count(*) AS items FROM l GROUP BY 1) SELECT step, items, round(s, 4) AS seconds, round(s / sum(s) OVER (), 6) AS share_span, round(CASE WHEN step <> 'error' THEN s END / sum(CASE WHEN step <> 'error' THEN s END) OVER (), 6) AS share_active FROM g")
_add("w15_batch_profile", A.batch_profile, f"WITH {_LOG}, g AS (SELECT step, batch, sum(seconds) AS s FROM l GROUP BY 1, 2) SELECT step, count(*) AS batches, round(avg(s), 4) AS mean, round(min(s), 4) AS least, round(max(s), 4) AS most FROM g GROUP BY 1")
_add("w15_drift", A.drift, f"WITH {_LOG}, g AS (SELECT step, batch, sum(seconds) AS s FROM l GROUP BY 1, 2) SELECT step, round(regr_slope(s, batch), 4) AS slope FROM g GROUP BY 1")
_CALLS = "calls AS (SELECT conv_id, turn, text AS request, CASE WHEN lead(role) OVER w = 'assistant' THEN lead(text) OVER w END AS response, role FROM conversations WINDOW w AS (PARTITION BY conv_id ORDER BY turn))"
_add("w17_api_cost", A.api_cost, f"WITH {_CALLS}, t AS (SELECT response, len(list_filter(regexp_split_to_array(coalesce(request, ''), '\\s+'), lambda x: x <> '')) AS n FROM calls WHERE role = 'user') SELECT count(*) AS requests, count(response) AS answered, sum(n)::BIGINT AS input_tokens, round(sum(n) * 0.075::DOUBLE * 0.875::DOUBLE / 1e6::DOUBLE, 9) AS cost FROM t")


def caption_outcome(spark, sf_dir):
    calls = C.caption_calls(spark, sf_dir)
    final = elements.finalize_caption(F.lit(True), F.col("response"))
    return calls.agg(F.count("*").alias("requests"), F.count_if(final == "CAPTION FAILED").alias("failed"), F.round(F.avg((final == "CAPTION FAILED").cast("int")), 6).alias("failure_rate"))


_add("w10_caption_outcome", caption_outcome, f"WITH {_CALLS} SELECT count(*) AS requests, count_if(response IS NULL OR trim(response) = '')::BIGINT AS failed, round(avg((response IS NULL OR trim(response) = '')::INT), 6) AS failure_rate FROM calls WHERE role = 'user'")

_WORDS = "w AS (SELECT doc_id, unnest(regexp_extract_all(coalesce(text, ''), '[^\\s]+')) AS t FROM documents)"


def _caption_tokens(spark, sf_dir):
    caption = elements.extractive_caption(F.col("text"))
    return C.read(spark, sf_dir, "documents").select("doc_id", F.split(caption, " ").alias("tokens")).where("tokens IS NOT NULL")


def token_stats(spark, sf_dir):
    n = F.size("tokens")
    return _caption_tokens(spark, sf_dir).agg(F.count("*").alias("captions"), F.round(F.avg(n), 6).alias("mean"), F.percentile(n, F.lit(0.5)).alias("median"), F.round(F.stddev(n), 6).alias("sd"), F.min(n).alias("least"), F.max(n).alias("most"), F.sum(n).alias("total"))


_add("w10_token_stats", token_stats, "WITH c AS (SELECT least(50, len(list_filter(regexp_split_to_array(coalesce(text, ''), '\\s+'), lambda x: x <> ''))) AS n FROM documents) SELECT count(*) AS captions, round(avg(n), 6) AS mean, quantile_cont(n, 0.5)::DOUBLE AS median, round(stddev(n), 6) AS sd, min(n)::INTEGER AS least, max(n)::INTEGER AS most, sum(n)::BIGINT AS total FROM c WHERE n > 0")


def _scored_captions(spark, sf_dir):
    """(doc_id, logprobs): the built-in provider's token log-probabilities, ln of the token's add-one share."""
    tokens = _caption_tokens(spark, sf_dir).select("doc_id", F.explode("tokens").alias("token"))
    counts = tokens.groupBy("token").agg(F.count("*").alias("c"))
    total = counts.agg(F.sum("c").alias("n"), F.count("*").alias("v"))
    shares = counts.join(F.broadcast(total), how="cross").select("token", F.log((F.col("c") + 1) / (F.col("n") + F.col("v"))).alias("lp"))
    return tokens.join(shares, "token").groupBy("doc_id").agg(F.array_sort(F.collect_list("lp")).alias("logprobs"))


def linear_probability(spark, sf_dir):
    s = _scored_captions(spark, sf_dir)
    return s.select("doc_id", F.round(mean_logprob(F.col("logprobs")), 6).alias("mean_logprob"), F.round(linear_prob(F.col("logprobs")), 6).alias("linear_prob"), F.round(F.array_min("logprobs"), 6).alias("worst"))


_SCORED = "c AS (SELECT doc_id, unnest(list_filter(regexp_split_to_array(coalesce(text, ''), '\\s+'), lambda x: x <> '')[1:50]) AS token FROM documents), k AS (SELECT token, count(*) AS c FROM c GROUP BY 1), s AS (SELECT doc_id, ln((k.c + 1)::DOUBLE / ((SELECT sum(c) FROM k) + (SELECT count(*) FROM k))::DOUBLE) AS lp FROM c JOIN k USING (token))"
_add("w10_linear_prob", linear_probability, f"WITH {_SCORED} SELECT doc_id, round(avg(lp), 6) AS mean_logprob, round(exp(avg(lp)), 6) AS linear_prob, round(min(lp), 6) AS worst FROM s GROUP BY 1")


def logprob_histogram(spark, sf_dir, sample: int = 10_000):
    s = linear_probability(spark, sf_dir).orderBy(F.md5(F.col("doc_id").cast("string"))).limit(sample)
    return s.groupBy(F.expr("width_bucket(mean_logprob, -12D, 0D, 24)").cast("int").alias("bin")).agg(F.count("*").alias("captions"))


_add("w10_logprob_hist", logprob_histogram, f"WITH {_SCORED}, m AS (SELECT doc_id, round(avg(lp), 6) AS x FROM s GROUP BY 1 ORDER BY md5(doc_id::VARCHAR) LIMIT 10000) SELECT CASE WHEN x < -12 THEN 0 WHEN x >= 0 THEN 25 ELSE floor((x + 12) * 2) + 1 END::INTEGER AS bin, count(*) AS captions FROM m GROUP BY 1")


def gram_counts(docs, n: int = 3):
    """(lang, gram, c): lower-case character n-grams of whole texts, each text walked once."""

    def run(batches):
        for batch in batches:
            counts: dict = {}
            for lang, text in zip(batch.column(0).to_pylist(), batch.column(1).to_pylist()):
                counts.setdefault(lang, Counter()).update(text[k : k + n] for k in range(max(len(text) - n + 1, 1)))
            for lang, c in counts.items():
                yield pa.RecordBatch.from_arrays([pa.array([lang] * len(c), pa.string()), pa.array(list(c), pa.string()), pa.array(list(c.values()), pa.int64())], names=["lang", "gram", "c"])

    lower = docs.select("lang", F.lower(F.coalesce("text", F.lit(""))).alias("text"))
    return lower.mapInArrow(run, "lang string, gram string, c bigint").groupBy("lang", "gram").agg(F.sum("c").alias("c"))


def language_profiles(docs, n: int = 3):
    """(lang, gram, weight): log shares of lower-case character n-grams."""
    c = gram_counts(docs, n)
    per = c.groupBy("lang").agg(F.sum("c").alias("total"), F.count("*").alias("v"))
    return c.join(F.broadcast(per), "lang").select("lang", "gram", F.log((F.col("c") + 1) / (F.col("total") + F.col("v"))).alias("weight"), F.log(1 / (F.col("total") + F.col("v"))).alias("unseen"))


def language_agreement(spark, sf_dir):
    """Requested against detected language of the captions of held-out documents."""
    docs = C.read(spark, sf_dir, "documents").withColumn("u", C.unit_hash("doc_id", "lang"))
    profiles = language_profiles(docs.where("u < 0.5").select("lang", "text"))
    caption = F.lower(elements.extractive_caption(F.col("text")))
    held = docs.where("u >= 0.5").select("doc_id", "lang", caption.alias("caption")).where("caption IS NOT NULL")
    grams = held.select("doc_id", "lang", F.explode(F.transform(F.sequence(F.lit(1), F.greatest(F.length("caption") - 2, F.lit(1))), lambda i: F.substring("caption", i, 3))).alias("gram")).groupBy("doc_id", "lang", "gram").agg(F.count("*").alias("n"))
    base = profiles.select("lang", "unseen").distinct().withColumnRenamed("lang", "guess")
    sizes = grams.groupBy("doc_id", "lang").agg(F.sum("n").alias("n"))
    hits = grams.join(profiles.withColumnRenamed("lang", "guess"), "gram").groupBy("doc_id", "guess").agg(F.sum(F.col("n") * (F.col("weight") - F.col("unseen"))).alias("gain"))
    scored = sizes.join(F.broadcast(base), how="cross").join(hits, ["doc_id", "guess"], "left").withColumn("score", F.col("n") * F.col("unseen") + F.coalesce("gain", F.lit(0.0)))
    best = scored.groupBy("doc_id", "lang").agg(F.max_by("guess", "score").alias("detected"))
    return best.groupBy("lang", "detected").agg(F.count("*").alias("captions"))


_add("w10_lang_agreement", language_agreement)


def thesaurus(spark, sf_dir):
    docs, bench = C.read(spark, sf_dir, "documents"), C.read(spark, sf_dir, "benchmark")
    word = F.explode(F.regexp_extract_all("text", F.lit(r"[\p{L}\p{N}]+"), F.lit(0)))
    top = bench.select(word.alias("surface")).select(F.lower("surface").alias("keyword")).where("length(keyword) >= 5").groupBy("keyword").agg(F.count("*").alias("c")).orderBy(F.desc("c"), "keyword").limit(50)
    terms = top.select("keyword", F.explode(F.array("keyword", F.concat(F.upper(F.substring("keyword", 1, 1)), F.expr("substring(keyword, 2)")))).alias("surface"))
    return elements.thesaurus_matches(docs, F.broadcast(terms.limit(100)))


_add("w11_thesaurus", thesaurus, "WITH b AS (SELECT lower(unnest(regexp_extract_all(text, '[\\p{L}\\p{N}]+'))) AS keyword FROM benchmark), top AS (SELECT keyword, count(*) AS c FROM b WHERE length(keyword) >= 5 GROUP BY 1 ORDER BY c DESC, keyword LIMIT 50), terms AS (SELECT keyword, unnest([keyword, upper(keyword[1]) || keyword[2:]]) AS surface FROM top), d AS (SELECT doc_id, unnest(regexp_extract_all(text, '[\\p{L}\\p{N}]+')) AS surface FROM documents) SELECT doc_id, keyword, surface, count(*) AS n FROM d JOIN terms USING (surface) GROUP BY ALL")

# ---- fingerprints and grouping

HASH_SQL = """t AS (SELECT doc_id, list_filter(regexp_split_to_array(lower(text), '\\s+'), lambda x: x <> '') AS w FROM documents WHERE text IS NOT NULL),
g AS (SELECT DISTINCT doc_id, array_to_string(w[i:i + 2], ' ') AS gram FROM (SELECT doc_id, w, unnest(range(1, greatest(len(w) - 2, 1) + 1)) AS i FROM t WHERE len(w) > 0)),
x AS (SELECT doc_id, unnest(range(1, 37)) AS p, md5(gram) || substr(md5(gram || '#1'), 1, 4) AS h FROM g),
d AS (SELECT doc_id, p, ('0x' || substr(h, p, 1))::INTEGER AS v FROM x),
b AS (SELECT doc_id, p, (CASE WHEN 2 * sum((v >> 3) & 1) > count(*) THEN 8 ELSE 0 END + CASE WHEN 2 * sum((v >> 2) & 1) > count(*) THEN 4 ELSE 0 END + CASE WHEN 2 * sum((v >> 1) & 1) > count(*) THEN 2 ELSE 0 END + CASE WHEN 2 * sum(v & 1) > count(*) THEN 1 ELSE 0 END) AS v FROM d GROUP BY ALL),
hashes AS (SELECT doc_id AS id, string_agg(lower(to_hex(v)), '' ORDER BY p) AS hash FROM b GROUP BY 1)"""
EDGE_SQL = HASH_SQL + """, words AS (SELECT id, hash, ('0x' || substr(hash, 1, 16))::UBIGINT AS a, ('0x' || substr(hash, 17, 16))::UBIGINT AS b, ('0x' || substr(hash, 33, 4))::UBIGINT AS c FROM hashes),
near AS (SELECT l.id AS src, r.id AS dst, l.hash AS lh, r.hash AS rh, bit_count(xor(l.a, r.a)) + bit_count(xor(l.b, r.b)) + bit_count(xor(l.c, r.c)) AS distance FROM words l JOIN words r ON l.id < r.id AND bit_count(xor(l.a, r.a)) + bit_count(xor(l.b, r.b)) + bit_count(xor(l.c, r.c)) <= 16),
banded AS (SELECT src, dst, distance::INTEGER AS distance FROM near WHERE """ + " OR ".join(f"substr(lh, {1 + 6 * k}, 6) = substr(rh, {1 + 6 * k}, 6)" for k in range(6)) + ")"
GROUP_SQL = """both_ways AS (SELECT src, dst FROM banded UNION SELECT dst, src FROM banded), reach(id, far) AS (SELECT doc_id, doc_id FROM documents UNION SELECT reach.id, both_ways.dst FROM reach JOIN both_ways ON reach.far = both_ways.src), hash_groups AS (SELECT id, min(far) AS group_id FROM reach GROUP BY 1)"""


def hashed_documents(spark, sf_dir):
    return fingerprints.kept(fingerprints.sign_hash(C.read(spark, sf_dir, "documents").select(F.col("doc_id").alias("id"), "text")).select("id", "hash"))


_add("w07_sign_hash", lambda s, d: hashed_documents(s, d).where("hash IS NOT NULL"), f"WITH {HASH_SQL} SELECT id, hash FROM hashes")
_add("w07_hash_edges", lambda s, d: dedup.banded_edges(hashed_documents(s, d)), f"WITH {EDGE_SQL} SELECT src, dst, distance FROM banded")
_add("w07_hash_groups", lambda s, d: dedup.hash_groups(hashed_documents(s, d)), f"WITH RECURSIVE {EDGE_SQL}, {GROUP_SQL} SELECT id, group_id FROM hash_groups")
_add("w07_exhaustive_edges", lambda s, d: dedup.exhaustive_edges(hashed_documents(s, d)), f"WITH {EDGE_SQL} SELECT src, dst, distance::INTEGER AS distance FROM near")
_add("w07_bucket_sizes", lambda s, d: dedup.bucket_sizes(hashed_documents(s, d)).groupBy("band", "members").agg(F.count("*").alias("buckets")), f"WITH {HASH_SQL}, r AS (SELECT unnest(range(0, 6)) AS band, hash FROM hashes), k AS (SELECT band, substr(hash, 1 + 6 * band, 6) AS value, count(*) AS members FROM r GROUP BY ALL) SELECT band::TINYINT AS band, members, count(*) AS buckets FROM k GROUP BY ALL")


def band_quality(spark, sf_dir):
    """Found and exhaustive pairs, and candidates met, of three ways to cut the hash into bands."""
    h = hashed_documents(spark, sf_dir)
    ways = ((6, 24), (9, 16), (18, 8))
    counts = fingerprints.kept(dedup.found_counts(h, [(bands, bits, 0) for bands, bits in ways]))
    rows = None
    for k, (bands, bits) in enumerate(ways):
        found = counts.select(F.col(f"found{k}").alias("found"), "exhaustive")
        met = dedup.bucket_sizes(h, bands, bits).agg(F.sum(F.col("members") * (F.col("members") - 1) / 2).cast("bigint").alias("candidates"), F.max("members").alias("largest_bucket"))
        one = found.join(met, how="cross").select(F.lit(bands).alias("bands"), F.lit(bits).alias("bits"), "found", "exhaustive", "candidates", "largest_bucket")
        rows = one if rows is None else rows.unionByName(one)
    return rows


def _quality_sql():
    parts = []
    for bands, bits in ((6, 24), (9, 16), (18, 8)):
        w = bits // 4
        shared = " OR ".join(f"substr(lh, {1 + w * k}, {w}) = substr(rh, {1 + w * k}, {w})" for k in range(bands))
        parts.append(f"SELECT {bands} AS bands, {bits} AS bits, (SELECT count(*) FROM near WHERE {shared}) AS found, (SELECT count(*) FROM near) AS exhaustive, sum(m * (m - 1) // 2)::BIGINT AS candidates, max(m) AS largest_bucket FROM (SELECT count(*) AS m FROM (SELECT hash, unnest(range(0, {bands})) AS band FROM hashes) GROUP BY band, substr(hash, 1 + {w} * band, {w}))")
    return f"WITH {EDGE_SQL} " + " UNION ALL ".join(parts)


_add("w07_band_quality", band_quality, _quality_sql())


def embedded_documents(spark, sf_dir, encoder="word3"):
    return fingerprints.kept(fingerprints.embed(C.read(spark, sf_dir, "documents").select(F.col("doc_id").alias("id"), "text"), encoder=encoder).select("id", "vec"))


def packed_documents(spark, sf_dir):
    return fingerprints.kept(fingerprints.packed(fingerprints.embed(C.read(spark, sf_dir, "documents").select(F.col("doc_id").alias("id"), "text")).select("id", "vec")))


VECTOR_SQL = """vb AS (SELECT doc_id, ('0x' || substr(md5(gram), 1, 8))::BIGINT % 512 AS k, sum(CASE WHEN substr(md5(gram), 9, 1) >= '8' THEN 1 ELSE -1 END)::DOUBLE AS w FROM g GROUP BY 1, 2),
cells AS (SELECT doc_id, k FROM (SELECT DISTINCT doc_id FROM g), (SELECT unnest(range(0, 512)) AS k)),
dense AS (SELECT doc_id AS id, list(coalesce(w, 0.0::DOUBLE) ORDER BY k) AS v FROM cells LEFT JOIN vb USING (doc_id, k) GROUP BY 1),
vec AS (SELECT id, v, sqrt(list_inner_product(v, v)) AS s FROM dense),
vnear AS (SELECT a.id AS src, b.id AS dst FROM vec a JOIN vec b ON a.id < b.id AND a.s > 0 AND b.s > 0 AND list_inner_product(a.v, b.v) >= 0.86::DOUBLE * a.s * b.s)"""
VECTOR_GROUP_SQL = """vboth AS (SELECT src, dst FROM vnear UNION SELECT dst, src FROM vnear), vreach(id, far) AS (SELECT doc_id, doc_id FROM documents UNION SELECT vreach.id, vboth.dst FROM vreach JOIN vboth ON vreach.far = vboth.src), vector_groups AS (SELECT id, min(far) AS group_id FROM vreach GROUP BY 1)"""
BOTH_SQL = "both_groups AS (SELECT h.id, min(h.id) OVER (PARTITION BY h.group_id, v.group_id) AS group_id FROM hash_groups h JOIN vector_groups v ON h.id = v.id)"
CASCADE_SQL = """reps AS (SELECT hash, min(id) AS id FROM hashes GROUP BY 1), met AS (SELECT src, dst FROM banded WHERE src IN (SELECT id FROM reps) AND dst IN (SELECT id FROM reps) UNION SELECT r.id, h.id FROM hashes h JOIN reps r ON h.hash = r.hash AND h.id > r.id),
ce AS (SELECT src, dst FROM met JOIN vec a ON a.id = src JOIN vec b ON b.id = dst WHERE list_inner_product(a.v, b.v) >= 0.86::DOUBLE * a.s * b.s), cboth AS (SELECT src, dst FROM ce UNION SELECT dst, src FROM ce),
creach(id, far) AS (SELECT doc_id, doc_id FROM documents UNION SELECT creach.id, cboth.dst FROM creach JOIN cboth ON creach.far = cboth.src), cascade_groups AS (SELECT id, min(far) AS group_id FROM creach GROUP BY 1)"""
ALL_GROUPS_SQL = f"WITH RECURSIVE {EDGE_SQL}, {GROUP_SQL}, {VECTOR_SQL}, {VECTOR_GROUP_SQL}, {BOTH_SQL}, {CASCADE_SQL}"
PLANTED_SQL = """p AS (SELECT vec_id, v, unnest(range(0, CASE WHEN vec_id % 7 = 0 THEN (vec_id // 7) % 12 + 2 ELSE 1 END)) AS k FROM (SELECT vec_id, list_transform(embedding, lambda x: x::DOUBLE) AS v FROM embeddings)),
m AS (SELECT vec_id, k, list_transform(range(1, len(v) + 1), lambda i: v[i] + 0.05::DOUBLE * k * v[(i - 1 + k) % len(v) + 1]) AS m FROM p),
planted AS (SELECT vec_id || ':' || k AS id, vec_id AS truth_group, list_transform(m, lambda x: x / sqrt(list_inner_product(m, m))) AS vec FROM m),
found AS (SELECT a.id AS src, b.id AS dst, a.truth_group = b.truth_group AS right_, list_inner_product(a.vec, b.vec) AS similarity FROM planted a JOIN planted b ON a.id < b.id AND list_inner_product(a.vec, b.vec) >= 0.86::DOUBLE)"""
_add("w08_vector_groups", lambda s, d: dedup.vector_groups(packed_documents(s, d)), f"WITH RECURSIVE {HASH_SQL}, {VECTOR_SQL}, {VECTOR_GROUP_SQL} SELECT id, group_id FROM vector_groups")
_add("w08_planted_edges", lambda s, d: dedup.cosine_edges(C.planted_vectors(s, d)).select("src", "dst", F.round("similarity", 6).alias("similarity")), f"WITH {PLANTED_SQL} SELECT src, dst, round(similarity, 6) AS similarity FROM found")


def planted_quality(spark, sf_dir):
    v = C.planted_vectors(spark, sf_dir).persist()
    truth = v.alias("a").join(v.alias("b"), (F.col("a.truth_group") == F.col("b.truth_group")) & (F.col("a.id") < F.col("b.id"))).select(F.col("a.id").alias("src"), F.col("b.id").alias("dst"))
    return dedup.pair_metrics(dedup.cosine_edges(v), truth)


_add("w08_planted_quality", planted_quality, f"WITH {PLANTED_SQL}, n AS (SELECT truth_group, count(*) AS n FROM planted GROUP BY 1), c AS (SELECT (SELECT count(*) FROM found) AS found, (SELECT sum(n * (n - 1) // 2)::BIGINT FROM n) AS truth, (SELECT count(*) FROM found WHERE right_) AS hits) SELECT found, truth, hits AS both, round(hits / found, 6)::DOUBLE AS precision, round(hits / truth, 6)::DOUBLE AS recall, round(2 * (hits / found) * (hits / truth) / (hits / found + hits / truth), 6)::DOUBLE AS f1 FROM c".replace("hits AS both", 'hits AS "both"'))


def ann_recall(spark, sf_dir):
    """Recall of every approximate search against the exact one, on the planted vectors."""
    v = C.planted_vectors(spark, sf_dir).select("id", "vec").persist()
    truth = knn.knn_exact(v, 10).persist()
    out = None
    for name, found in (("graph", knn.knn_graph(v, 10, shards=2)), ("cells", knn.knn_cells(v, 10)), ("hyperplanes", knn.knn_hyperplanes(v, 10))):
        one = knn.recall(found, truth).select(F.lit(name).alias("method"), "truth", "found", "recall")
        out = one if out is None else out.unionByName(one)
    return out


_add("w08_ann_recall", ann_recall)


def strategies(spark, sf_dir):
    prints = fingerprints.kept(fingerprints.packed(fingerprints.fingerprint(C.read(spark, sf_dir, "documents").select(F.col("doc_id").alias("id"), "text"))))
    h, v = prints.select("id", "hash"), prints.select("id", "packed")
    by_hash, by_vector = dedup.hash_groups(h), dedup.vector_groups(v)
    ways = (("hash", by_hash), ("vector", by_vector), ("both", dedup.intersect_groups(by_hash, by_vector).select("id", "group_id")), ("cascade", dedup.cascade_groups(h, v)))
    out = None
    for name, groups in ways:
        one = dedup.group_stats(groups).select(F.lit(name).alias("strategy"), "*")
        out = one if out is None else out.unionByName(one)
    return out


_STATS = "SELECT '{0}' AS strategy, sum(m)::BIGINT AS elements, count(*) AS groups, round(1 - count(*) / sum(m), 6)::DOUBLE AS reduction, round(avg((m = 1)::INT), 6) AS singleton_share, max(m) AS largest FROM (SELECT count(*) AS m FROM {1} GROUP BY group_id)"
_add("w09_strategies", strategies, ALL_GROUPS_SQL + " " + " UNION ALL ".join(_STATS.format(a, b) for a, b in (("hash", "hash_groups"), ("vector", "vector_groups"), ("both", "both_groups"), ("cascade", "cascade_groups"))))
_add("w09_largest_groups", lambda s, d: collection.largest_groups(dedup.hash_groups(hashed_documents(s, d))), f"WITH RECURSIVE {EDGE_SQL}, {GROUP_SQL} SELECT group_id, count(*) AS members, min(id) AS first, max(id) AS last FROM hash_groups GROUP BY 1 ORDER BY members DESC, group_id LIMIT 10")
_add("w09_group_sizes", lambda s, d: dedup.group_sizes(dedup.hash_groups(hashed_documents(s, d))), f"WITH RECURSIVE {EDGE_SQL}, {GROUP_SQL}, s AS (SELECT group_id, count(*) AS members FROM hash_groups GROUP BY 1) SELECT members, count(*) AS groups FROM s GROUP BY 1")
_add("w09_cascade", lambda s, d: dedup.cascade_groups(hashed_documents(s, d), packed_documents(s, d)), ALL_GROUPS_SQL + " SELECT id, group_id FROM cascade_groups")


def sweep_vectors(spark, sf_dir):
    """Best threshold and its precision, recall and F1 for each encoder, against word n-gram overlap."""
    docs = C.read(spark, sf_dir, "documents").select(F.col("doc_id").alias("id"), "text")
    names = ["word3", "word1", "char3", "char1"]

    def run(batches):
        seen = {}
        for batch in batches:
            texts = batch.column(batch.schema.names.index("text")).to_pylist()
            found = [[fingerprints.counts(t, *fingerprints.ENCODERS[name], seen) for t in texts] for name in names]
            packed = [pa.array([None if v is None else zlib.compress(v.tobytes(), 6) for v in one], pa.binary()) for one in found]
            yield pa.RecordBatch.from_arrays([batch.column(batch.schema.names.index("class")), *packed], names=["class", *names])

    rows = fingerprints.kept(sweeps.with_class(fingerprints.spread(docs)).mapInArrow(run, ", ".join(["class bigint", *(f"{name} binary" for name in names)])))
    # every pair is scored: a baseline is judged over its whole range
    return sweeps.best_of(rows, sweeps.true_pairs(docs), {name: sweeps.cosine() for name in names}, names, "encoder")


_add("w06_sweep_vectors", sweep_vectors)


def sweep_hashes(spark, sf_dir):
    """The same for sizes of the sign hash and of the cosine-transform hash, by distance."""
    docs = C.read(spark, sf_dir, "documents").select(F.col("doc_id").alias("id"), "text")
    signs, sides = (64, 144, 256), (8, 12, 16, 24)
    names = ["sign", *(f"dct{side}" for side in sides)]

    def run(batches):
        for batch in batches:
            texts = batch.column(batch.schema.names.index("text")).to_pylist()
            found = [[fingerprints.sign_bytes(t, max(signs)) for t in texts]] + [[np.packbits(fingerprints.dct_bits(fingerprints.text_grid(t, 4 * side), side)).tobytes() for t in texts] for side in sides]
            yield pa.RecordBatch.from_arrays([batch.column(batch.schema.names.index("class")), *(pa.array(one, pa.binary()) for one in found)], names=["class", *names])

    rows = fingerprints.kept(sweeps.with_class(fingerprints.spread(docs)).mapInArrow(run, ", ".join(["class bigint", *(f"{name} binary" for name in names)])))
    # a shorter sign hash is the beginning of a longer one
    kinds = {"sign": sweeps.bits(*signs)} | {f"dct{side}": sweeps.bits(side * side) for side in sides}
    return sweeps.best_of(rows, sweeps.true_pairs(docs), kinds, [f"sign{bits}" for bits in signs] + names[1:], "hash")


_add("w06_sweep_hashes", sweep_hashes)

# ---- classes, detection, orientation, release


def quality_metrics(spark, sf_dir):
    """A rule on repeated lines and word lengths against the human quality label."""
    rows = C.read(spark, sf_dir, "documents").join(C.read(spark, sf_dir, "labels"), "doc_id")
    words = F.size(F.filter(F.split(F.coalesce("text", F.lit("")), r"\s+"), lambda w: w != ""))
    marks = F.length(F.regexp_replace(F.coalesce("text", F.lit("")), r"[^#$%&*|]", ""))
    good = (words >= 20) & (marks * 10 < words)
    return elements.class_metrics(rows.select(F.col("quality").alias("truth"), good.cast("int").alias("predicted")))


_add("w04_class_metrics", quality_metrics, "WITH r AS (SELECT quality AS t, (len(list_filter(regexp_split_to_array(coalesce(text, ''), '\\s+'), lambda x: x <> '')) >= 20 AND length(regexp_replace(coalesce(text, ''), '[^#$%&*|]', '', 'g')) * 10 < len(list_filter(regexp_split_to_array(coalesce(text, ''), '\\s+'), lambda x: x <> '')))::INTEGER AS p FROM documents JOIN labels USING (doc_id)), l AS (SELECT t AS label FROM r UNION SELECT p FROM r), c AS (SELECT label, (SELECT count(*) FROM r WHERE t = label) AS support, (SELECT count(*) FROM r WHERE p = label) AS predicted, (SELECT count(*) FROM r WHERE p = label AND t = label) AS correct FROM l) SELECT label, support, predicted, correct, round(correct / nullif(predicted, 0), 6) AS precision, round(correct / nullif(support, 0), 6) AS recall FROM c")


def split_table(spark, sf_dir):
    d = A.document_elements(spark, sf_dir).withColumn("split", elements.split_of("id"))
    return d.groupBy("raw_class", "split").agg(F.count("*").alias("n"))


_add("w04_split_table", split_table, f"WITH {A.ELEMENTS_SQL}, s AS (SELECT raw_class, ('0x' || substr(md5(id || ':split'), 1, 8))::BIGINT / 4294967296.0::DOUBLE AS v FROM elements) SELECT raw_class, CASE WHEN v < 0.8 THEN 'train' WHEN v < 0.9 THEN 'val' ELSE 'test' END AS split, count(*) AS n FROM s GROUP BY ALL")


def music_modes(spark, sf_dir):
    d = A.document_elements(spark, sf_dir)
    caption = elements.extractive_caption(F.col("text"))
    kept = [F.count_if(elements.music_guard(F.col("raw_class"), F.col("class_confidence"), caption, A.MUSIC_TERMS, 0.99, m) == "music").alias(m) for m in ("confidence", "keywords", "both")]
    return d.agg(F.count_if(F.col("raw_class") == "music").alias("music"), *kept)


_add("w05_music_guard", music_modes, f"WITH {A.ELEMENTS_SQL}, m AS (SELECT class_confidence >= 0.99 AS sure, regexp_matches(coalesce(array_to_string(list_filter(regexp_split_to_array(coalesce(text, ''), '\\s+'), lambda x: x <> '')[1:50], ' '), ''), '(?i)(?:^|[^\\p{{L}}\\p{{N}}])(?:the|und|que|les)(?:$|[^\\p{{L}}\\p{{N}}])') AS named FROM elements WHERE raw_class = 'music') SELECT count(*) AS music, count_if(sure)::BIGINT AS confidence, count_if(named)::BIGINT AS keywords, count_if(sure OR named)::BIGINT AS both FROM m")


def detect_pages(spark, sf_dir):
    """Blocks found per class, and those at or above the dataset's cutoff."""
    return elements.blocks(C.read(spark, sf_dir, "pages")).groupBy("truth_class").agg(F.count("*").alias("blocks"), F.count_if(F.col("confidence") >= 0.75).alias("kept"), F.count_distinct("page_id").alias("pages"))


_add("w01_detect_pages", detect_pages)


def suppressed(spark, sf_dir):
    """Detections that survive suppression of overlaps, volume by volume."""
    d = C.detections(spark, sf_dir).withColumnRenamed("detection_confidence", "confidence").withColumnRenamed("key", "id")
    return elements.nms(d, "volume_id").select("volume_id", "id", F.round("confidence", 6).alias("confidence"))


_add("w01_nms", suppressed)


def orient_metrics(spark, sf_dir):
    rows = elements.rotations(C.read(spark, sf_dir, "documents").select(F.col("doc_id").alias("id"), "text")).where("split = 'test'")
    scored = elements.orientation_scores(rows).withColumn("said", (F.array_position("scores", F.array_max("scores")).cast("int") - 1) * 90)
    return scored.rollup("target").agg(F.count("*").alias("total"), F.count_if(F.col("said") == F.col("target")).alias("correct"))


_add("w12_orient_metrics", orient_metrics)
_add("w12_rotations", lambda s, d: elements.rotations(C.read(s, d, "documents").select(F.col("doc_id").alias("id"))).groupBy("split", "degrees", "target").agg(F.count("*").alias("n")), "WITH r AS (SELECT doc_id, unnest([0, 90, 180, 270]) AS degrees, ('0x' || substr(md5(doc_id || ':split'), 1, 8))::BIGINT / 4294967296.0::DOUBLE AS v FROM documents) SELECT CASE WHEN v < 0.8 THEN 'train' WHEN v < 0.9 THEN 'val' ELSE 'test' END AS split, degrees, (360 - degrees) % 360 AS target, count(*) AS n FROM r GROUP BY ALL")


def gate_sweep(spark, sf_dir):
    rows = elements.rotations(C.read(spark, sf_dir, "documents").select(F.col("doc_id").alias("id"), "text")).where("split = 'test'")
    scored = elements.orientation_scores(rows)
    gates = F.explode(F.array(*[F.lit(x) for x in (0.5, 0.7, 0.9, 0.95, 0.99)]))
    best = F.array_max("scores")
    said = (F.array_position("scores", best).cast("int") - 1) * 90
    g = scored.select("target", best.alias("p"), said.alias("said"), gates.alias("gate"))
    turned = (F.col("p") >= F.col("gate")) & (F.col("said") != 0)
    return g.groupBy("gate").agg(F.count_if(turned).alias("rotated"), F.count_if(turned & (F.col("said") != F.col("target"))).alias("wrongly"), F.count_if(~turned & (F.col("target") != 0)).alias("missed"))


_add("w12_gate_sweep", gate_sweep)
_add("w13_prepare", A.flagship, f"""{ALL_GROUPS_SQL}, {A.ELEMENTS_SQL}, sure AS (SELECT e.*, h.group_id FROM elements e JOIN both_groups h USING (id) WHERE detection_confidence >= 0.75),
best AS (SELECT group_id, arg_max(id, (detection_confidence, -id)) AS id FROM sure GROUP BY 1), f AS (SELECT s.*, nullif(array_to_string(list_filter(regexp_split_to_array(coalesce(text, ''), '\\s+'), lambda x: x <> '')[1:50], ' '), '') AS caption FROM sure s JOIN best USING (id))
SELECT id, barcode_src, length(text)::INTEGER AS width_gen, 48 AS height_gen, round(greatest(length(text), 1) * 48 / 1e6, 6) AS pixel_count_mpx_gen, round(detection_confidence, 6) AS detection_confidence_gen, CASE WHEN class_confidence < 0.70 THEN 'other' WHEN raw_class = 'music' AND NOT (class_confidence >= 0.99 OR regexp_matches(coalesce(caption, ''), '(?i)(?:^|[^\\p{{L}}\\p{{N}}])(?:the|und|que|les)(?:$|[^\\p{{L}}\\p{{N}}])')) THEN 'other' ELSE raw_class END AS classification_gen,
round(class_confidence, 6) AS classification_confidence_gen, CASE WHEN raw_class NOT IN ('decorative', 'artifact') THEN coalesce(caption, 'CAPTION FAILED') END AS caption_exp FROM f""")
_add("w13_record", A.full_record)


def leakage(spark, sf_dir):
    splits = C.read(spark, sf_dir, "documents").select(F.col("doc_id").alias("id")).withColumn("split", elements.split_of("id"))
    return elements.split_leakage(splits, dedup.hash_groups(hashed_documents(spark, sf_dir)))


_add("w16_split_leakage", leakage, f"WITH RECURSIVE {EDGE_SQL}, {GROUP_SQL}, s AS (SELECT group_id, CASE WHEN v < 0.8 THEN 'train' WHEN v < 0.9 THEN 'val' ELSE 'test' END AS split FROM (SELECT group_id, ('0x' || substr(md5(id || ':split'), 1, 8))::BIGINT / 4294967296.0::DOUBLE AS v FROM hash_groups)), p AS (SELECT group_id, count(DISTINCT split) AS k, count(*) AS m FROM s GROUP BY 1) SELECT count(*) AS groups, count_if(k > 1)::BIGINT AS leaking_groups, coalesce(sum(CASE WHEN k > 1 THEN m END), 0)::BIGINT AS leaking_members FROM p")
