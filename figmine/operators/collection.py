"""Steps around the models: annotation sets, class vectors, requests, releases, budgets. All are plain DataFrame plans."""

from __future__ import annotations

import json
import time
from dataclasses import asdict, dataclass

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame, Window
from pyspark.sql import functions as F

from ..config import CLASSES, DEFAULT

# ---- annotation sets and pages


def with_negatives(pages: DataFrame, annotations: DataFrame, page: str = "page_id") -> DataFrame:
    """Every page with its number of annotations, pages without any included."""
    counts = annotations.groupBy(page).agg(F.count("*").alias("annotations"))
    return pages.join(counts, page, "left").withColumn("annotations", F.coalesce("annotations", F.lit(0)))


def merge_classes(annotations: DataFrame, label: str = "label", into: str = "element") -> DataFrame:
    """All labels as one, for a detector that finds regions and leaves their kind to another model."""
    return annotations.withColumn(label, F.lit(into))


def pages_with_hits(pages: DataFrame, detections: DataFrame, page: str = "page_id") -> DataFrame:
    """Only the pages that hold a detection: put before any decoding, which cannot be pruned afterwards."""
    return pages.join(detections.select(page).distinct(), page, "left_semi")


def assign_round_robin(rows: DataFrame, devices: int, key: str) -> DataFrame:
    """``rows`` with ``device``: even shares, the same for a key on every run."""
    return rows.withColumn("device", F.pmod(F.xxhash64(key), F.lit(devices)).cast("int"))


@dataclass(frozen=True)
class TrainConfig:
    # fixed values: the published training settings of the detector
    size: int = 800
    box_weight: float = 8.3
    distribution_weight: float = 1.5
    scale: float = 0.7
    patience: int = 50
    most_epochs: int = 400
    mixed_precision: bool = True
    deterministic: bool = True


# ---- class vectors


def softmax(scores, labels=CLASSES, sharpness: float = 8.0):
    """array<struct(label, prob)> of scores (one column a label), most likely first, ties by label."""
    powers = [F.exp(F.lit(sharpness) * s) for s in scores]
    total = sum(powers[1:], powers[0])
    pairs = F.array(*[F.struct(F.lit(n).alias("label"), (p / total).alias("prob")) for n, p in zip(labels, powers)])
    order = lambda a, b: F.when(a["prob"] > b["prob"], -1).when(a["prob"] < b["prob"], 1).when(a["label"] < b["label"], -1).otherwise(1)
    return F.array_sort(pairs, order)


def top1(probs):
    """Most likely class and its probability, as a struct."""
    return F.get(probs, 0)


def prob_of(probs, label: str):
    return F.coalesce(F.get(F.filter(probs, lambda p: p["label"] == label), F.lit(0))["prob"], F.lit(0.0))


def redecide(probs, cuts: dict[str, float], fallback: str = "other"):
    """Another decision from stored probabilities, without the model: the most likely class that reaches its own cut."""
    wanted = F.create_map(*[F.lit(x) for pair in cuts.items() for x in pair])
    kept = F.filter(probs, lambda p: p["prob"] >= F.coalesce(F.try_element_at(wanted, p["label"]), F.lit(0.0)))
    return F.coalesce(F.get(kept, 0)["label"], F.lit(fallback))


def train_classifier(rows: DataFrame, features: list[str], label: str):
    """A multinomial classifier over numeric columns; ``rows`` is an annotation set, small beside the collection."""
    from pyspark.ml import Pipeline
    from pyspark.ml.classification import LogisticRegression
    from pyspark.ml.feature import StandardScaler, StringIndexer, VectorAssembler

    return Pipeline(
        stages=[
            StringIndexer(inputCol=label, outputCol="_label", stringOrderType="alphabetAsc"),
            VectorAssembler(inputCols=features, outputCol="_raw"),
            StandardScaler(inputCol="_raw", outputCol="_features", withMean=True),
            LogisticRegression(featuresCol="_features", labelCol="_label", probabilityCol="_prob", rawPredictionCol="_logits", predictionCol="_best", regParam=0.01),
        ]
    ).fit(rows.where(F.col(label).isNotNull()))


def classify(rows: DataFrame, model) -> DataFrame:
    """``rows`` with ``probs``, array<struct(label, prob)> most likely first."""
    from pyspark.ml.functions import vector_to_array

    labels = model.stages[0].labels
    indexer, rest = model.stages[0], model.stages[1:]
    _ = indexer
    out = rows
    for stage in rest:
        out = stage.transform(out)
    values = vector_to_array("_prob")
    pairs = F.array(*[F.struct(F.lit(n).alias("label"), values[k].alias("prob")) for k, n in enumerate(labels)])
    order = lambda a, b: F.when(a["prob"] > b["prob"], -1).when(a["prob"] < b["prob"], 1).when(a["label"] < b["label"], -1).otherwise(1)
    return out.withColumn("probs", F.array_sort(pairs, order)).drop("_raw", "_features", "_logits", "_prob", "_best")


# ---- grids


def grayscale(channels: np.ndarray) -> np.ndarray:
    """Height x width x 3 to height x width, by integer weights."""
    return (channels.astype(np.int64) @ np.array([299, 587, 114])) // 1000


def resize(grid: np.ndarray, height: int, width: int) -> np.ndarray:
    rows = np.arange(height) * grid.shape[0] // height
    columns = np.arange(width) * grid.shape[1] // width
    return grid[rows][:, columns]


def to_batch(grids: list[np.ndarray], side: int, fit: str = "stack") -> np.ndarray:
    """Grids of any shape as one batch. ``resize`` distorts each to a square, ``pad`` puts all into the largest frame and
    shrinks that, ``stack`` keeps each aspect and centres it."""
    if fit == "resize":
        return np.stack([resize(g, side, side) for g in grids])
    if fit == "pad":
        height, width = max(g.shape[0] for g in grids), max(g.shape[1] for g in grids)
        frames = []
        for g in grids:
            frame = np.zeros((height, width), g.dtype)
            frame[: g.shape[0], : g.shape[1]] = g
            frames.append(resize(frame, side, side))
        return np.stack(frames)
    out = np.zeros((len(grids), side, side), grids[0].dtype)
    for k, g in enumerate(grids):
        scale = side / max(g.shape)
        h, w = max(1, round(g.shape[0] * scale)), max(1, round(g.shape[1] * scale))
        y, x = (side - h) // 2, (side - w) // 2
        out[k, y : y + h, x : x + w] = resize(g, h, w)
    return out


def to_tensor(grid: np.ndarray, side: int = 224, mean=(0.485, 0.456, 0.406), std=(0.229, 0.224, 0.225)) -> np.ndarray:
    """Channels first, each standardised; a gray grid counts as three equal channels."""
    if grid.ndim == 2:
        grid = np.repeat(grid[:, :, None], 3, axis=2)
    small = resize(grid, side, side) / 255.0
    return ((small - np.array(mean)) / np.array(std)).transpose(2, 0, 1)


# ---- captions


def build_requests(elements: DataFrame, pages: DataFrame, languages: DataFrame, instruction: str, page: str = "page_id", code: str = "language_src") -> DataFrame:
    """``elements`` with ``request``: JSON of the instruction, the same page's text, the crop and the caption's language."""
    named = resolve_language(elements, languages, code)
    rows = named.join(pages.select(page, F.col("text").alias("page_text")), page, "left")
    content = F.array(
        F.struct(F.lit("text").alias("type"), F.concat_ws("\n", F.coalesce("page_text", F.lit("")), F.concat(F.lit("Language: "), F.col("caption_language"))).alias("body")),
        F.struct(F.lit("image").alias("type"), F.coalesce("payload", F.lit("")).alias("body")),
    )
    return rows.withColumn("request", F.to_json(F.struct(F.lit(instruction).alias("system"), content.alias("content")))).drop("page_text")


def resolve_language(rows: DataFrame, languages: DataFrame, code: str = "language_src") -> DataFrame:
    """``rows`` with ``caption_code`` (three letters) and ``caption_language`` (its name); English where unknown.

    ``languages`` is the code list (code2, code3, name): a few hundred rows whatever the collection.
    """
    names = F.broadcast(languages.select("code2", "code3", "name").dropDuplicates(["code2"]))
    j = rows.join(names, F.lower(F.trim(F.col(code))) == F.col("code2"), "left")
    return j.withColumn("caption_code", F.coalesce("code3", F.lit("eng"))).withColumn("caption_language", F.coalesce("name", F.lit("English"))).drop("code2", "code3", "name")


def encode_payload(rows: DataFrame, grid: str = "grid", most: int = 1248) -> DataFrame:
    """``rows`` with ``payload``: base64 of the grid struct(h, w, px), shrunk so that no side is over ``most``."""

    @F.arrow_udf("string")
    def pack(grids: pa.Array) -> pa.Array:
        import base64

        out = []
        for g in grids.to_pylist():
            if g is None or not g["px"]:
                out.append(None)
                continue
            px = np.array(g["px"], np.uint8).reshape(g["h"], g["w"])
            scale = min(1.0, most / max(px.shape))
            small = resize(px, max(1, int(px.shape[0] * scale)), max(1, int(px.shape[1] * scale)))
            out.append(base64.b64encode(small.shape[0].to_bytes(2, "big") + small.shape[1].to_bytes(2, "big") + small.tobytes()).decode())
        return pa.array(out, pa.string())

    return rows.withColumn("payload", pack(grid))


def pack_logprobs(tokens):
    """array<struct(token, logprob)> as text, as it is stored; ``unpack_logprobs`` gives it back."""
    return F.to_json(tokens)


def unpack_logprobs(text):
    return F.from_json(text, "array<struct<token:string,logprob:double>>")


def text_reliance(caption, page_text, n: int = 3):
    """Share of a caption's word n-grams that stand in the page's text: near 1, the caption repeats the page."""

    def grams(c):
        words = F.filter(F.split(F.lower(F.coalesce(c, F.lit(""))), r"\s+"), lambda w: w != "")
        whole = F.array(F.array_join(words, " "))
        return F.when(F.size(words) == 0, F.array().cast("array<string>")).when(F.size(words) < n, whole).otherwise(F.array_distinct(F.transform(F.sequence(F.lit(1), F.greatest(F.size(words) - n + 1, F.lit(1))), lambda i: F.array_join(F.slice(words, i, n), " "))))

    own = grams(caption)
    return F.when(F.size(own) > 0, F.size(F.array_intersect(own, grams(page_text))) / F.size(own))


# ---- grouping


def components_local(pairs: list[tuple], nodes=()) -> dict:
    """Node to smallest reachable node, by union-find with path halving: for graphs known to be small."""
    parent = {x: x for x in nodes}

    def root(x):
        parent.setdefault(x, x)
        while parent[x] != x:
            parent[x] = parent[parent[x]]
            x = parent[x]
        return x

    for a, b in pairs:
        x, y = root(a), root(b)
        if x != y:
            parent[max(x, y)] = min(x, y)
    return {x: root(x) for x in list(parent)}


def largest_groups(groups: DataFrame, top: int = 10) -> DataFrame:
    """(group_id, members, first, last) of the ``top`` largest groups, ties to the smaller id."""
    sizes = groups.groupBy("group_id").agg(F.count("*").alias("members"), F.min("id").alias("first"), F.max("id").alias("last"))
    return sizes.orderBy(F.desc("members"), "group_id").limit(top)


def write_groups(groups: DataFrame, path: str, method: str) -> None:
    """One table a method, overwritten as a whole when it is run again."""
    groups.write.mode("overwrite").parquet(f"{path}/method={method}")


def dedup_increment(fresh: DataFrame, known: DataFrame, tau: int = 16, bands: int = 6, bits: int = 24) -> DataFrame:
    """(id, group_id) of a new batch against grouped history.

    ``fresh`` has (id, hash), ``known`` (id, hash, group_id). Only pairs with a new end are looked at; a new element joins
    the smallest group it reaches. Groups of the history that a new element connects come out as rows of their own ids.
    """
    from ..functions.expressions import hamming
    from .dedup import band_records
    from .graph import components

    a = band_records(fresh, bands, bits).select("band", "value", F.col("id").alias("src"), F.col("words").alias("x"))
    b = band_records(known.select("id", "hash").unionByName(fresh.select("id", "hash")), bands, bits).select("band", "value", F.col("id").alias("dst"), F.col("words").alias("y"))
    pairs = a.join(b, ["band", "value"]).where((F.col("src") != F.col("dst")) & (hamming(F.col("x"), F.col("y")) <= tau)).select("src", "dst").distinct()
    # a known element stands for its group
    home = known.select(F.col("id").alias("dst"), "group_id")
    edges = pairs.join(home, "dst", "left").select("src", F.coalesce("group_id", "dst").alias("dst"))
    found = components(edges)
    out = fresh.select("id").join(found, F.col("id") == F.col("node"), "left").select("id", F.coalesce("component", "id").alias("group_id"))
    moved = known.join(found, F.col("group_id") == F.col("node")).where("component < group_id").select("id", F.col("component").alias("group_id"))
    return out.unionByName(moved)


# ---- features kept between runs


def cached(rows: DataFrame, path: str, feature: str, settings: dict, key: str, compute) -> DataFrame:
    """The feature table of ``rows``: what a run with the same settings has left under ``path``, and ``compute`` for the
    keys it lacks. Thresholds are no settings of a feature, so a new threshold reads and computes nothing."""
    import hashlib

    spark = rows.sparkSession
    mark = hashlib.md5(json.dumps(settings, sort_keys=True).encode()).hexdigest()[:12]
    place = f"{path}/feature={feature}/settings={mark}"
    where = spark._jvm.org.apache.hadoop.fs.Path(place)
    if where.getFileSystem(spark._jsc.hadoopConfiguration()).exists(where):
        missing = rows.join(spark.read.parquet(place).select(key), key, "left_anti")
        if not missing.isEmpty():
            compute(missing).write.mode("append").parquet(place)
    else:
        compute(rows).write.parquet(place)
    return spark.read.parquet(place).join(rows.select(key), key, "left_semi")


# ---- checks by people


def review_sample(rows: DataFrame, key: str, stratum: str, n: int = 20) -> DataFrame:
    """``n`` rows of each stratum, drawn by the md5 of the key."""
    w = Window.partitionBy(stratum).orderBy(F.md5(F.col(key).cast("string")), key)
    return rows.withColumn("_r", F.row_number().over(w)).where(F.col("_r") <= n).drop("_r")


def borderline(rows: DataFrame, column: str, cut: float, width: float) -> DataFrame:
    return rows.where(F.abs(F.col(column) - cut) <= width)


def describe_dataset(df: DataFrame, keys=("id",)) -> str:
    """A guide that programs can read: name, type and origin of each column."""
    origin = {"_src": "source", "_gen": "generated", "_exp": "experimental"}
    return json.dumps({"columns": [{"name": f.name, "type": f.dataType.simpleString(), "origin": origin.get(f.name[-4:], "key" if f.name in keys else "unknown")} for f in df.schema.fields], "settings": asdict(DEFAULT)})


# ---- budgets


def timed(df: DataFrame) -> dict:
    """Rows, seconds and rows a second of a plan, run into nothing."""
    observed = F.count(F.lit(1)).alias("rows")
    from pyspark.sql import Observation

    seen = Observation()
    t = time.time()
    df.observe(seen, observed).write.format("noop").mode("overwrite").save()
    took = time.time() - t
    return {"rows": seen.get["rows"], "seconds": took, "per_second": seen.get["rows"] / max(took, 1e-9)}


def curve_report(log: DataFrame, epoch: str = "epoch", train: str = "train_loss", validation: str = "val_loss") -> DataFrame:
    """Each epoch with the change of both losses and whether it overfits: training still falls, validation rises."""
    w = Window.orderBy(epoch)
    down, up = F.col(train) - F.lag(train).over(w), F.col(validation) - F.lag(validation).over(w)
    return log.select("*", down.alias("train_change"), up.alias("val_change"), F.coalesce((down < 0) & (up > 0), F.lit(False)).alias("overfits"))


def skew_guard(counts: DataFrame, size: str = "n", factor: float = 10.0) -> DataFrame:
    """``counts`` with ``parts``: into how many parts a volume is dealt so that none is over ``factor`` medians."""
    middle = counts.agg(F.percentile_approx(size, 0.5).alias("middle"))
    return counts.crossJoin(F.broadcast(middle)).withColumn("parts", F.greatest(F.lit(1), F.ceil(F.col(size) / (F.greatest("middle", F.lit(1)) * factor))).cast("int")).drop("middle")


def rights_filter(rows: DataFrame, allowed: list[str], column: str = "rights") -> DataFrame:
    """Only what may be released; an unknown status may not."""
    return rows.where(F.coalesce(F.col(column).isin(allowed), F.lit(False)))
