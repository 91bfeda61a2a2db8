import numpy as np
import pytest
from pyspark.sql import functions as F
from pyspark.sql import types as T

from figmine.functions import expressions as E
from figmine.operators import dedup, elements, fingerprints, graph, knn


def box(*v):
    return {k: F.lit(float(x)) for k, x in zip(("x0", "y0", "x1", "y1"), v)}


def test_iou(spark):
    got = spark.range(1).select(E.iou(box(0, 0, 2, 2), box(4, 4, 5, 5)), E.iou(box(0, 0, 2, 2), box(0, 0, 2, 2)), E.iou(box(0, 0, 2, 1), box(1, 0, 3, 1))).first()
    assert got[0] == 0 and got[1] == 1 and abs(got[2] - 1 / 3) < 1e-12


def test_nms_keeps_what_only_a_dropped_box_overlaps(spark):
    rows = [("p", "a", 0.9, 0.0, 0.0, 10.0, 10.0), ("p", "b", 0.8, 5.0, 0.0, 15.0, 10.0), ("p", "c", 0.7, 12.0, 0.0, 22.0, 10.0)]
    got = elements.nms(spark.createDataFrame(rows, "page string, id string, confidence double, x0 double, y0 double, x1 double, y1 double"))
    assert {r["id"] for r in got.collect()} == {"a", "c"}


def flip(hexed, bits):
    v = int(hexed, 16)
    for b in bits:
        v ^= 1 << (143 - b)
    return f"{v:036x}"


def test_banding_by_distance(spark):
    zero = "0" * 36
    spread5 = flip(zero, [0, 24, 48, 72, 96])
    every_band = flip(zero, [0, 24, 48, 72, 96, 120])
    at16, at17 = flip(zero, range(16)), flip(zero, range(17))
    h = spark.createDataFrame([(0, zero), (1, spread5), (2, every_band), (3, at16), (4, at17), (5, None)], "id long, hash string")
    got = {(r["src"], r["dst"]): r["distance"] for r in dedup.banded_edges(h).collect()}
    full = {(r["src"], r["dst"]): r["distance"] for r in dedup.exhaustive_edges(h).collect()}
    assert got[0, 1] == 5 and (0, 2) not in got and full[0, 2] == 6
    assert got[0, 3] == 16 and (0, 4) not in full
    assert set(got) <= set(full)


@pytest.mark.parametrize(
    "edges,want",
    [
        ([(k, k + 1) for k in range(8)], {k: 0 for k in range(9)}),
        ([(5, 9), (9, 5), (7, 7), (1, 2)], {5: 5, 9: 5, 7: 7, 1: 1, 2: 1}),
        ([(0, 1), (1, 2), (2, 0)], {0: 0, 1: 0, 2: 0}),
    ],
)
def test_components(spark, edges, want):
    got = graph.components(spark.createDataFrame(edges, "src long, dst long"))
    assert {r["node"]: r["component"] for r in got.collect()} == want


def test_components_of_nothing(spark):
    assert graph.components(spark.createDataFrame([], "src long, dst long")).count() == 0


def test_sign_hash_forms_agree(spark):
    rows = spark.createDataFrame([(0, "a b c d"), (1, "one"), (2, ""), (3, None), (4, "x y  z\nx y z")], "id long, text string")
    fast = {r["id"]: r["hash"] for r in fingerprints.sign_hash(rows).collect()}
    slow = {r["id"]: r["hash"] for r in fingerprints.sign_hash_sql(rows, "id").collect()}
    assert fast[2] is None and fast[3] is None
    assert {k: v for k, v in fast.items() if v} == slow


def test_rotation_is_undone_by_its_target():
    g = np.arange(12).reshape(3, 4)
    for d in (0, 90, 180, 270):
        assert (elements.rotate(elements.rotate(g, d), (360 - d) % 360) == g).all()


def test_class_rules(spark):
    rows = spark.createDataFrame([(0.6999, "music", None), (0.70, "music", "a song"), (0.9899, "music", "none"), (0.99, "music", None)], "p double, raw string, caption string")
    label = elements.relabel_other(F.col("raw"), F.col("p"))
    got = [r[0] for r in rows.select(elements.music_guard(label, F.col("p"), F.col("caption"), ["song"])).collect()]
    assert got == ["other", "music", "other", "music"]


def test_representative_prefers_confidence_then_small_id(spark):
    rows = spark.createDataFrame([(1, 1, 0.5), (2, 1, 0.9), (3, 1, 0.9)], "id long, group_id long, detection_confidence double")
    assert dedup.representatives(rows).first()["id"] == 2


def test_graph_search_recall(spark):
    rng = np.random.default_rng(0)
    v = rng.normal(size=(300, 16))
    v /= np.linalg.norm(v, axis=1, keepdims=True)
    rows = spark.createDataFrame([(k, x.tolist()) for k, x in enumerate(v)], "id long, vec array<double>")
    truth = knn.knn_exact(rows, 5, shards=2)
    assert knn.recall(knn.knn_graph(rows, 5, shards=2), truth).first()["recall"] >= 0.9


def test_strategies_refine(spark):
    g = lambda rows: spark.createDataFrame(rows, "id long, group_id long")
    both = dedup.intersect_groups(g([(0, 0), (1, 0), (2, 0)]), g([(0, 0), (1, 0), (2, 2)]))
    assert {r["id"]: r["group_id"] for r in both.collect()} == {0: 0, 1: 0, 2: 2}


def test_failed_calls_are_retried_and_then_null(spark):
    def provider(request):
        if request == "bad":
            raise OSError
        return request.upper()

    rows = spark.createDataFrame([("ok",), ("bad",)], "request string")
    got = {r["request"]: r["response"] for r in elements.run_captions(rows, provider).collect()}
    assert got == {"ok": "OK", "bad": None}


def test_best_epoch_stops_at_patience(spark):
    log = spark.createDataFrame([(1, 0.5), (2, 0.6), (3, 0.55), (4, 0.5), (5, 0.9)], "epoch int, value double")
    assert elements.best_epoch(log, 2, 10).first()["epoch"] == 2


def test_release_keeps_what_only_one_grouping_joins(spark, tmp_path):
    import hashlib

    from figmine.plans import analysis

    sure = [k for k in range(100) if int(hashlib.md5(f"{k}:det".encode()).hexdigest()[:8], 16) / 2**32 > 0.65][:3]
    near = "w21 w20 w105 w348 w132 w285 w161 "  # with either ending: 15 bits apart, cosine 0.83
    texts = [near + "w187", near + "w190", near + "w187"]
    spark.createDataFrame([(k, t, "en", "s") for k, t in zip(sure, texts)], "doc_id long, text string, lang string, source string").write.parquet(str(tmp_path / "documents.parquet"))
    hashed = fingerprints.sign_hash(spark.read.parquet(str(tmp_path / "documents.parquet")).select(F.col("doc_id").alias("id"), "text"))
    assert {r["group_id"] for r in dedup.hash_groups(hashed.select("id", "hash")).collect()} == {sure[0]}
    groups = {r["id"]: r["group_id"] for r in analysis.release_groups(fingerprints.fingerprint(hashed.select("id", "text"))).collect()}
    assert groups == {sure[0]: sure[0], sure[1]: sure[1], sure[2]: sure[0]}
    got = analysis.full_record(spark, str(tmp_path))
    assert [f.name for f in got.schema] == [f.name for f in T.StructType.fromDDL(analysis.FINAL_SCHEMA)] and len(got.columns) == 22
    assert analysis.check_suffixes(got) == [] and got.count() == 2


def test_language_profiles_read_whole_texts(spark):
    from figmine.plans import chain_queries

    rows = spark.createDataFrame([("en", "ab " * 60 + "xyz"), ("en", None), ("de", "Ü")], "lang string, text string")
    got = {(r["lang"], r["gram"]): r["c"] for r in chain_queries.gram_counts(rows).collect()}
    assert got["en", "xyz"] == 1 and got["en", "ab "] == 60 and got["en", ""] == 1 and got["de", "ü"] == 1


def test_near_hashes_without_comparing_all_pairs(spark):
    rng = np.random.default_rng(5)
    base = [int.from_bytes(rng.bytes(18), "big") for _ in range(10)] + [0, (1 << 144) - 1]
    numbers = base + [b ^ sum(1 << int(k) for k in rng.choice(144, int(rng.integers(0, 19)), replace=False)) for b in base for _ in range(12)]
    # one bit in each band but one, where none does; two bits in all bands but two, where one does
    numbers += [sum(1 << 16 * k for k in range(8)), sum(3 << 16 * k for k in range(2, 9)) | 1 << 3 | 1 << 29]
    rows = spark.createDataFrame([(k, f"{x:036x}") for k, x in enumerate(numbers)] + [(999, None)], "id int, hash string")
    truth = {(a, b, (x ^ y).bit_count()) for a, x in enumerate(numbers) for b, y in enumerate(numbers) if a < b and (x ^ y).bit_count() <= 16}
    found = dedup.exhaustive_edges(rows)
    assert "NestedLoop" not in found._jdf.queryExecution().toString() and "CartesianProduct" not in found._jdf.queryExecution().toString()
    got = list(map(tuple, found.collect()))
    assert len(got) == len(set(got)) and set(got) == truth
    ways = [(6, 24, 0), (9, 16, 0), (18, 8, 0), (6, 24, 1)]
    counts = dedup.found_counts(rows, ways).first()
    assert counts["exhaustive"] == len(truth)
    for k, (bands, bits, probes) in enumerate(ways):
        assert counts[f"found{k}"] == dedup.probed_edges(rows, 16, bands, bits, probes).count()
        assert probes or counts[f"found{k}"] == dedup.banded_edges(rows, 16, bands, bits).count()
    none = dedup.found_counts(rows.where("hash IS NULL"), ways).first()
    assert set(none) == {0} and dedup.exhaustive_edges(rows.where("hash IS NULL")).count() == 0


def test_vector_groups_are_searched_by_heads(spark):
    rng = np.random.default_rng(7)
    base = rng.normal(size=(8, 64))
    v = np.concatenate([base[k % 8] + rng.uniform(0, 0.9) * rng.normal(size=64) for k in range(90)]).reshape(90, 64)
    v /= np.linalg.norm(v, axis=1, keepdims=True)
    v[70:] = v[3]  # a class of equal vectors
    rows = spark.createDataFrame([(k, x.tolist()) for k, x in enumerate(v)] + [(90, None)], "id long, vec array<double>")
    kept = fingerprints.packed(rows)
    assert {r["id"]: r["v"] for r in kept.select("id", fingerprints.unpacked(F.col("packed")).alias("v")).collect()} == {r["id"]: r["vec"] for r in rows.collect()}
    label = np.arange(90)
    sims = v @ v.T
    for _ in range(90):
        label = np.array([label[sims[k] >= 0.86].min() for k in range(90)])
    want = dict(enumerate(label.tolist())) | {90: 90}
    for tile in (16, 1000):
        edges = dedup.near_vectors(kept, tile=tile)
        assert {r["id"]: r["group_id"] for r in dedup.vector_groups(kept, edges=edges).collect()} == want
    assert len(set(want.values())) < 60 and edges.where("src = 3 AND dst >= 70").count() == 20
    assert {r["id"]: r["group_id"] for r in dedup.vector_groups(rows).collect()} == want
    assert dedup.vector_groups(rows.where("vec IS NULL")).first()["group_id"] == 90


def test_release_and_strategies_keep_vectors_packed(spark, tmp_path):
    from figmine.plans import analysis, chain_queries

    texts = ["one two three four five six seven eight", "one two three four five six seven eight", "quite other words stand in this one", "", None]
    spark.createDataFrame([(k, t, "en", "s") for k, t in enumerate(texts)], "doc_id long, text string, lang string, source string").write.parquet(str(tmp_path / "documents.parquet"))
    release, prints = analysis.released(spark, str(tmp_path))
    assert prints.columns == ["id", "hash", "packed"]
    vectors = {r["id"]: r["vec"] for r in fingerprints.fingerprint(spark.read.parquet(str(tmp_path / "documents.parquet")).withColumnRenamed("doc_id", "id")).collect()}
    record = analysis.release_record(spark, str(tmp_path), release, prints).collect()
    assert {r["id"]: r["embedding_gen"] and np.float64(r["embedding_gen"]).tolist() for r in record} == {r["id"]: vectors[r["id"]] for r in record}
    assert [tuple(r)[:3] for r in chain_queries.strategies(spark, str(tmp_path)).collect()] == [(name, 5, 4) for name in ("hash", "vector", "both", "cascade")]


def test_exact_neighbours_hold_a_bounded_block(monkeypatch):
    rng = np.random.default_rng(2)
    c = rng.normal(size=(60, 8))
    c[50:] = c[3]  # ties
    sims = c @ c.T
    monkeypatch.setattr(knn, "HELD", 130)
    for k in (1, 5, 100):
        got = knn._best(np.arange(60), c, np.arange(60), c, k).groupby("id")["neighbour"].apply(list).to_dict()
        want = {r: [int(t) for t in np.argsort(-np.where(np.arange(60) == r, -np.inf, sims[r]), kind="stable")[:k] if t != r] for r in range(60)}
        assert {r: set(x) for r, x in got.items()} == {r: set(x) for r, x in want.items()} or k < 100
        assert all(len(x) == min(k, 59) and r not in x for r, x in got.items())
        assert all(np.allclose(sims[r][got[r]], sims[r][want[r]]) for r in want)
