import json

import numpy as np
import pytest
from pyspark.sql import functions as F

from figmine.operators import collection as K
from figmine.operators import dedup, fingerprints
from figmine.streaming import streams


def rows(df):
    return sorted(map(tuple, df.collect()), key=str)


def test_annotation_sets(spark):
    pages = spark.createDataFrame([(1,), (2,), (3,)], "page_id int")
    marks = spark.createDataFrame([(1, "a"), (1, "b"), (3, "c")], "page_id int, label string")
    assert rows(K.with_negatives(pages, marks)) == [(1, 2), (2, 0), (3, 1)]
    assert rows(K.pages_with_hits(pages, marks)) == [(1,), (3,)]
    assert {r["label"] for r in K.merge_classes(marks).collect()} == {"element"}
    assert K.with_negatives(pages, marks.limit(0)).agg(F.sum("annotations")).first()[0] == 0
    assert {r["device"] for r in K.assign_round_robin(spark.range(100), 4, "id").collect()} == {0, 1, 2, 3}


def test_class_vectors(spark):
    one = spark.range(1).select(K.softmax([F.lit(x) for x in (0.1, 0.9, 0.5, 0.9, 0.0)]).alias("p"))
    p = one.first()["p"]
    assert [x["label"] for x in p[:2]] == ["artifact", "chart"] and abs(sum(x["prob"] for x in p) - 1) < 1e-9
    assert one.select(K.top1(F.col("p"))["label"]).first()[0] == "artifact"
    assert one.select(K.redecide(F.col("p"), {"artifact": 0.99}), K.redecide(F.col("p"), {x: 1.1 for x in ("illustration", "artifact", "decorative", "chart", "music")})).first()[:] == ("chart", "other")
    assert one.select(K.prob_of(F.col("p"), "none")).first()[0] == 0.0


def test_trained_classes(spark):
    given = spark.createDataFrame([(float(k), float(k % 7), "ab"[k > 50]) for k in range(100)], "x double, y double, label string")
    model = K.train_classifier(given, ["x", "y"], "label")
    got = K.classify(given.drop("label"), model)
    assert got.columns == ["x", "y", "probs"]
    right = sum((r["probs"][0]["label"] == "ab"[r["x"] > 50]) for r in got.collect())
    assert right >= 95


def test_grids():
    g = np.arange(12).reshape(3, 4)
    assert K.resize(g, 3, 4).tolist() == g.tolist() and K.resize(g, 6, 8)[5, 7] == 11
    assert K.to_batch([g, g.T], 8, "resize").shape == K.to_batch([g, g.T], 8, "pad").shape == K.to_batch([g, g.T], 8).shape == (2, 8, 8)
    assert K.to_batch([g + 1], 8)[0][0].sum() == 0  # the longer side fills the square, the other is centred
    assert K.grayscale(np.full((2, 2, 3), 7)).tolist() == [[7, 7], [7, 7]]
    assert K.to_tensor(g, 5).shape == (3, 5, 5)


def test_requests(spark):
    iso = spark.createDataFrame([("de", "deu", "German"), ("de", "ger", "German")], "code2 string, code3 string, name string")
    rows_ = spark.createDataFrame([(1, " DE", {"h": 1, "w": 2, "px": [1, 2]}), (2, None, None), (3, "xx", {"h": 0, "w": 0, "px": []})], "page_id int, language_src string, grid struct<h:int,w:int,px:array<int>>")
    pages = spark.createDataFrame([(1, "Seite"), (2, None)], "page_id int, text string")
    got = {r["page_id"]: r for r in K.build_requests(K.encode_payload(rows_), pages, iso, "Say what you see.").collect()}
    assert {k: r["caption_code"] for k, r in got.items()} == {1: "deu", 2: "eng", 3: "eng"}
    body = json.loads(got[1]["request"])
    assert body["system"] == "Say what you see." and body["content"][0]["body"] == "Seite\nLanguage: German" and body["content"][1]["body"]
    assert json.loads(got[2]["request"])["content"][1]["body"] == ""


def test_caption_measures(spark):
    df = spark.createDataFrame([("a b c d", "x a b c d y"), ("a b", "a b"), (None, "a"), ("p q r s", None)], "c string, t string")
    assert [r[0] for r in df.select(K.text_reliance(F.col("c"), F.col("t"))).collect()] == [1.0, 1.0, None, 0.0]
    tokens = spark.range(1).select(F.array(F.struct(F.lit("a").alias("token"), F.lit(-0.5).alias("logprob"))).alias("t"))
    assert tokens.select(K.unpack_logprobs(K.pack_logprobs(F.col("t")))[0]["logprob"]).first()[0] == -0.5


def test_local_components_and_groups(spark, tmp_path):
    assert K.components_local([(3, 2), (2, 5), (7, 8), (9, 9)], [1]) == {1: 1, 2: 2, 3: 2, 5: 2, 7: 7, 8: 7, 9: 9}
    groups = spark.createDataFrame([(1, 1), (2, 1), (3, 3), (4, 4), (5, 4)], "id long, group_id long")
    assert rows(K.largest_groups(groups, 2)) == [(1, 2, 1, 2), (4, 2, 4, 5)]
    K.write_groups(groups, str(tmp_path), "hash")
    K.write_groups(groups, str(tmp_path), "hash")
    assert spark.read.parquet(str(tmp_path)).count() == 5


def test_increment_equals_grouping_all(spark):
    base = "one two three four five six seven eight nine ten eleven twelve thirteen fourteen"
    texts = [base, base + " a", "quite other words are here and more of them to come", base + " b", "a third text with nothing of the others in it at all", base]
    hashed = fingerprints.kept(fingerprints.sign_hash(spark.createDataFrame(list(enumerate(texts)), "id long, text string")).select("id", "hash"))
    old, new = hashed.where("id < 3"), hashed.where("id >= 3")
    known = old.join(dedup.hash_groups(old, 40), "id")
    got = {r["id"]: r["group_id"] for r in K.dedup_increment(new, known, 40).collect()}
    whole = {r["id"]: r["group_id"] for r in dedup.hash_groups(hashed, 40).collect()}
    assert {k: v for k, v in got.items() if k >= 3} == {k: v for k, v in whole.items() if k >= 3}


def test_features_are_kept(spark, tmp_path):
    calls = []

    def compute(df):
        calls.append(df.count())
        return df.select("id", (F.col("id") * 2).alias("x"))

    for n, settings in ((3, {"side": 12}), (5, {"side": 12}), (5, {"side": 8})):
        got = K.cached(spark.range(n), str(tmp_path), "hash", settings, "id", compute)
        assert rows(got) == [(k, 2 * k) for k in range(n)]
    assert calls == [3, 2, 5]


def test_budgets(spark):
    assert K.timed(spark.range(1000))["rows"] == 1000
    log = spark.createDataFrame([(1, 1.0, 1.0), (2, 0.8, 0.9), (3, 0.6, 0.95)], "epoch int, train_loss double, val_loss double")
    assert [r["overfits"] for r in K.curve_report(log).orderBy("epoch").collect()] == [False, False, True]
    counts = spark.createDataFrame([(k, 4) for k in range(9)] + [(9, 200)], "volume_id int, n int")
    assert {r["volume_id"]: r["parts"] for r in K.skew_guard(counts).collect()}[9] == 5
    assert K.rights_filter(spark.createDataFrame([("pd",), ("ic",), (None,)], "rights string"), ["pd"]).count() == 1
    assert K.borderline(counts, "n", 200, 1).count() == 1 and K.review_sample(counts, "volume_id", "n", 3).count() == 4
    guide = json.loads(K.describe_dataset(spark.createDataFrame([(1, 2)], "id int, width_gen int")))
    assert [c["origin"] for c in guide["columns"]] == ["key", "generated"]


def test_batched_fingerprints_are_those_of_the_reference_form(spark):
    df = spark.createDataFrame([(0, "a b c d e"), (1, "one"), (2, None), (3, " ")], "id long, text string")
    both = {r["id"]: r for r in fingerprints.fingerprint(df).collect()}
    plain = {r["id"]: r["hash"] for r in fingerprints.sign_hash_sql(df, "id").collect()}
    assert {k: r["hash"] for k, r in both.items() if r["hash"]} == plain and both[2]["vec"] is None
    assert {r["id"]: r["vec"] for r in fingerprints.embed(df).collect()} == {k: r["vec"] for k, r in both.items()}


def test_forest_edges_keep_components(spark):
    rng = np.random.default_rng(1)
    base = rng.normal(size=(6, 16))
    v = [(k, (base[k % 6] + 0.01 * rng.normal(size=16)).tolist()) for k in range(60)]
    df = spark.createDataFrame(v, "id long, vec array<double>").select("id", F.transform("vec", lambda x: x / F.sqrt(F.aggregate("vec", F.lit(0.0), lambda a, y: a + y * y))).alias("vec"))
    full, few = (dedup.cosine_edges(df, 0.9, tile=16, forest=f) for f in (False, True))
    assert few.count() < full.count() == 6 * 45
    assert rows(dedup.vector_groups(df, 0.9)) == [(k, k % 6) for k in sorted(range(60), key=lambda k: str((k, k % 6)))]


@pytest.mark.parametrize("name", sorted(streams.LATER))
def test_streams_equal_their_batch_twins(spark, tmp_path, name):
    spark.createDataFrame([(k, f"2024-01-01 {k // 60 % 24:02d}:{k % 60:02d}:00", k % 5, ["click", "error", "view"][k % 3], float(k), "{}") for k in range(900)], "event_id long, ts string, user_id long, event_type string, value double, props string").withColumn("ts", F.col("ts").cast("timestamp_ntz")).write.parquet(str(tmp_path / "events.parquet"))
    spark.createDataFrame([(c, t, ["user", "assistant"][t % 2], "x") for c in range(20) for t in range(c % 5)], "conv_id long, turn long, role string, text string").write.parquet(str(tmp_path / "conversations.parquet"))
    stream, batch = streams.LATER[name]
    assert rows(stream(spark, str(tmp_path))) == rows(batch(spark, str(tmp_path)))


def test_sessions_do_not_pass_through_the_driver(spark, tmp_path):
    minutes = [(0, 1), (10, 1), (39, 1), (70, 1), (5, 2), (95, 2), (50, None)]
    made = spark.createDataFrame([(f"2024-01-01 {m // 60:02d}:{m % 60:02d}:00", u) for m, u in minutes], "ts string, user_id long").withColumn("ts", F.col("ts").cast("timestamp_ntz"))
    made.union(spark.createDataFrame([(None, 7)], made.schema)).write.parquet(str(tmp_path / "events.parquet"))
    got = streams.QUERIES["op_stream_session"](spark, str(tmp_path))
    at = "2024-01-01 0{}:00".format
    assert rows(got) == sorted([(at("0:00"), 1, 3), (at("1:10"), 1, 1), (at("0:05"), 2, 1), (at("1:35"), 2, 1), (at("0:50"), None, 1)], key=str)
    assert got.inputFiles()
    made.limit(0).write.parquet(str(tmp_path / "none" / "events.parquet"))
    assert streams.all_sessions(spark, str(tmp_path / "none")).count() == 0


def test_added_rows_are_drained_into_files(spark, tmp_path):
    spark.createDataFrame([(1, "view"), (2, None), (3, "other")], "event_id long, event_type string").write.parquet(str(tmp_path / "events.parquet"))
    got = streams.QUERIES["op_stream_static_join"](spark, str(tmp_path))
    assert got.inputFiles() and rows(got) == [(1, 2), (2, 0), (3, 0)]
