"""Detections and crops: suppression of overlaps, class decisions, splits, orientation, captions."""

from __future__ import annotations

import re

import numpy as np
import pandas as pd
import pyarrow as pa
from pyspark.sql import DataFrame, Window
from pyspark.sql import functions as F

from ..config import CAPTION_FAILED
from ..functions.expressions import iou

# ---- detection

BLOCK_CLASSES = {"article": "illustration", "ul": "chart", "li": "chart", "nav": "decorative", "footer": "decorative", "script": "artifact", "style": "artifact", "h1": "music"}


def block_pattern() -> str:
    """A block of any known tag but list items, which lie within lists."""
    return "(?is)" + "|".join(rf"<{tag}\b[^>]*>.*?</{tag}>" for tag in BLOCK_CLASSES if tag != "li")


def blocks(pages: DataFrame) -> DataFrame:
    """(page_id, block_no, tag, truth_class, confidence): html blocks as the regions of a page.

    Confidence grows with the share of a block's characters that are text and not markup.
    """
    pattern = block_pattern()
    found = pages.select("page_id", F.posexplode(F.regexp_extract_all("html", F.lit(pattern), F.lit(0))).alias("block_no", "raw"))
    tag = F.lower(F.regexp_extract("raw", r"^<(\w+)", 1))
    text = F.regexp_replace("raw", r"<[^>]*>", "")
    share = F.length(text) / F.greatest(F.length("raw"), F.lit(1))
    mapping = F.create_map(*[F.lit(x) for kv in BLOCK_CLASSES.items() for x in kv])
    return found.select("page_id", "block_no", tag.alias("tag"), F.element_at(mapping, tag).alias("truth_class"), F.round(0.3 + 0.7 * share, 6).alias("confidence"), F.length("raw").alias("size"))


def nms(boxes: DataFrame, page: str = "page", threshold: float = 0.20) -> DataFrame:
    """Greedy suppression within a page: by confidence, then id; a box stays if it overlaps no kept one by more."""
    rows = F.sort_array(F.collect_list(F.struct((-F.col("confidence")).alias("c"), F.col("id"), "x0", "y0", "x1", "y1")))
    kind = "array<struct<c:double,id:string,x0:double,y0:double,x1:double,y1:double>>"
    kept = F.aggregate(F.col("b"), F.array().cast(kind), lambda acc, b: F.when(F.exists(acc, lambda k: iou(k, b) > threshold), acc).otherwise(F.concat(acc, F.array(b))))
    cast = boxes.select(page, F.col("id").cast("string").alias("id"), *[F.col(c).cast("double").alias(c) for c in ("confidence", "x0", "y0", "x1", "y1")])
    out = cast.groupBy(page).agg(rows.cast(kind).alias("b")).select(page, F.explode(kept).alias("k"))
    return out.select(page, "k.id", (-F.col("k.c")).alias("confidence"), "k.x0", "k.y0", "k.x1", "k.y1")


def match_boxes(predicted: DataFrame, truth: DataFrame, page: str = "page", least: float = 0.5) -> DataFrame:
    """One row: predictions, truths, matches one to one, precision and recall; the surest prediction chooses first."""
    pairs = predicted.alias("p").join(truth.alias("t"), page).withColumn("v", iou({k: F.col(f"p.{k}") for k in ("x0", "y0", "x1", "y1")}, {k: F.col(f"t.{k}") for k in ("x0", "y0", "x1", "y1")})).where(F.col("v") >= least)
    ranked = pairs.groupBy(page).agg(F.sort_array(F.collect_list(F.struct((-F.col("p.confidence")).alias("c"), (-F.col("v")).alias("v"), F.col("p.id").cast("string").alias("p"), F.col("t.id").cast("string").alias("t")))).alias("m"))
    empty = F.array().cast("array<struct<c:double,v:double,p:string,t:string>>")
    chosen = F.aggregate("m", empty, lambda acc, x: F.when(F.exists(acc, lambda k: (k["p"] == x["p"]) | (k["t"] == x["t"])), acc).otherwise(F.concat(acc, F.array(x.cast("struct<c:double,v:double,p:string,t:string>")))))
    both = ranked.agg(F.coalesce(F.sum(F.size(chosen)), F.lit(0)).alias("matched"))
    n, m = predicted.agg(F.count("*").alias("predicted")), truth.agg(F.count("*").alias("truth"))
    one = both.withColumn("k", F.lit(1)).join(n.withColumn("k", F.lit(1)), "k").join(m.withColumn("k", F.lit(1)), "k")
    return one.select("predicted", "truth", "matched", F.round(F.col("matched") / F.when(F.col("predicted") > 0, F.col("predicted")), 6).alias("precision"), F.round(F.col("matched") / F.when(F.col("truth") > 0, F.col("truth")), 6).alias("recall"))


def split_of(key: str, salt: str = "split", ratios=(0.8, 0.1, 0.1)):
    from ..sources.carriers import unit_hash

    u = unit_hash(key, salt)
    return F.when(u < ratios[0], "train").when(u < ratios[0] + ratios[1], "val").otherwise("test")


def stratified_split(rows: DataFrame, key: str, stratum: str, ratios=(0.8, 0.1, 0.1)) -> DataFrame:
    from ..sources.carriers import unit_hash

    u = F.percent_rank().over(Window.partitionBy(stratum).orderBy(unit_hash(key, "split"), key))
    return rows.withColumn("split", F.when(u < ratios[0], "train").when(u < ratios[0] + ratios[1], "val").otherwise("test"))


def split_leakage(splits: DataFrame, groups: DataFrame) -> DataFrame:
    """One row: groups, those with members in several splits, and members of those."""
    per = splits.join(groups, "id").groupBy("group_id").agg(F.count_distinct("split").alias("splits"), F.count("*").alias("members"))
    return per.agg(F.count("*").alias("groups"), F.count_if(F.col("splits") > 1).alias("leaking_groups"), F.coalesce(F.sum(F.when(F.col("splits") > 1, F.col("members"))), F.lit(0)).alias("leaking_members"))


def best_epoch(log: DataFrame, patience: int, most: int) -> DataFrame:
    """One row (epoch, value): the best validation before it failed to improve for ``patience`` epochs."""
    order = Window.orderBy("epoch")
    runs = log.where(F.col("epoch") <= most).withColumn("best", F.max("value").over(order)).withColumn("earlier", F.max("value").over(order.rowsBetween(Window.unboundedPreceding, -1)))
    runs = runs.withColumn("last_gain", F.max(F.when(F.col("earlier").isNull() | (F.col("value") > F.col("earlier")), F.col("epoch"))).over(order))
    stopped = runs.withColumn("stop", F.min(F.when(F.col("epoch") - F.col("last_gain") >= patience, F.col("epoch"))).over(Window.partitionBy()))
    return stopped.where("stop IS NULL OR epoch <= stop").orderBy(F.desc("value"), "epoch").limit(1).select("epoch", "value")


def merge_annotations(proposed: DataFrame, corrected: DataFrame) -> DataFrame:
    """Corrections win over proposals of the same page and box number; both sides' other rows stay."""
    j = proposed.alias("p").join(corrected.alias("c"), ["page", "box"], "full_outer")
    return j.select("page", "box", F.coalesce("c.label", "p.label").alias("label"), F.when(F.col("c.label").isNotNull(), "human").otherwise("model").alias("origin"))


def escalate(rows: DataFrame, judge, low: float, high: float, confidence: str = "confidence") -> DataFrame:
    """Only scores between ``low`` and ``high`` go to the expensive judge (a DataFrame to DataFrame function)."""
    borderline = F.col(confidence).between(low, high)
    return rows.where(~borderline).unionByName(judge(rows.where(borderline)))


def first_component_map(activations: np.ndarray) -> np.ndarray:
    """Heat map of channels x h x w activations on their first principal component, by power iteration."""
    c = activations.reshape(len(activations), -1).astype(float)
    c = c - c.mean(axis=1, keepdims=True)
    cov, v = c @ c.T, np.ones(len(c)) / np.sqrt(len(c))
    for _ in range(200):
        w = cov @ v
        size = np.linalg.norm(w)
        if size == 0:
            break
        v, old = w / size, v
        if np.abs(v - old).max() < 1e-12:
            break
    return (v @ c).reshape(activations.shape[1:])


# ---- classes


def relabel_other(raw, confidence, least: float = 0.70):
    return F.when(confidence < least, "other").otherwise(raw)


def music_guard(label, confidence, caption, terms: list[str], least: float = 0.99, mode: str = "both"):
    """Music stays if it is sure or its caption names a musical thing, or by one of the two alone."""
    sure = confidence >= least
    named = F.coalesce(caption, F.lit("")).rlike(r"(?i)(?:^|[^\p{L}\p{N}])(?:" + "|".join(re.escape(t) for t in terms) + r")(?:$|[^\p{L}\p{N}])")
    stays = {"confidence": sure, "keywords": named, "both": sure | named}[mode]
    return F.when((label == "music") & ~stays, "other").otherwise(label)


def expand_terms(terms: DataFrame, translations: DataFrame, elements: DataFrame, top: int = 20) -> DataFrame:
    """(lang, term): the terms in the languages that most elements of the class have."""
    langs = elements.groupBy("lang").agg(F.count("*").alias("n")).orderBy(F.desc("n"), "lang").limit(top)
    return translations.join(terms, "keyword").join(F.broadcast(langs), "lang").select("lang", "term").distinct()


def class_metrics(rows: DataFrame, truth: str = "truth", predicted: str = "predicted") -> DataFrame:
    """(label, support, predicted, correct, precision, recall)."""
    flat = rows.select(F.explode(F.array(F.struct(F.col(truth).alias("label"), F.lit(1).alias("t"), F.lit(0).alias("p"), (F.col(truth) == F.col(predicted)).cast("int").alias("b")), F.struct(F.col(predicted).alias("label"), F.lit(0).alias("t"), F.lit(1).alias("p"), F.lit(0).alias("b")))).alias("x")).select("x.*")
    g = flat.groupBy("label").agg(F.sum("t").alias("support"), F.sum("p").alias("predicted"), F.sum("b").alias("correct"))
    return g.select("label", "support", "predicted", "correct", F.round(F.col("correct") / F.when(F.col("predicted") > 0, F.col("predicted")), 6).alias("precision"), F.round(F.col("correct") / F.when(F.col("support") > 0, F.col("support")), 6).alias("recall"))


# ---- grids and orientation


def rotate(grid: np.ndarray, degrees: int) -> np.ndarray:
    """Clockwise by a multiple of 90 degrees."""
    return np.rot90(grid, -(degrees // 90) % 4)


def letterbox(grid: np.ndarray, side: int, fill: int = 0) -> np.ndarray:
    """Nearest-neighbour resize that keeps the aspect and pads to a square."""
    h, w = grid.shape[:2]
    s = side / max(h, w)
    nh, nw = max(1, round(h * s)), max(1, round(w * s))
    small = grid[np.minimum((np.arange(nh) / s).astype(int), h - 1)][:, np.minimum((np.arange(nw) / s).astype(int), w - 1)]
    out = np.full((side, side, *grid.shape[2:]), fill, grid.dtype)
    top, left = (side - nh) // 2, (side - nw) // 2
    out[top : top + nh, left : left + nw] = small
    return out


def crop(grid: np.ndarray, x0: int, y0: int, x1: int, y1: int) -> np.ndarray:
    return grid[max(0, y0) : y1, max(0, x0) : x1]


def center_crop(grid: np.ndarray, side: int) -> np.ndarray:
    top, left = (grid.shape[0] - side) // 2, (grid.shape[1] - side) // 2
    return grid[top : top + side, left : left + side]


def augment(grid: np.ndarray, kind: str, amount: float, seed: int) -> np.ndarray:
    """One seeded transform: flip, invert, autocontrast, erase, translate, scale or jitter."""
    rng = np.random.default_rng(seed)
    g = grid.astype(float)
    if kind == "flip":
        g = g[:, ::-1] if rng.random() < amount else g
    elif kind == "invert":
        g = 255 - g if rng.random() < amount else g
    elif kind == "autocontrast":
        low, high = g.min(), g.max()
        g = (g - low) * 255 / (high - low) if rng.random() < amount and high > low else g
    elif kind == "erase":
        if rng.random() < amount:
            h, w = g.shape[0] // 3, g.shape[1] // 3
            y, x = rng.integers(0, g.shape[0] - h + 1), rng.integers(0, g.shape[1] - w + 1)
            g = g.copy()
            g[y : y + h, x : x + w] = 0
    elif kind == "translate":
        g = np.roll(g, (int(rng.uniform(-amount, amount) * g.shape[0]), int(rng.uniform(-amount, amount) * g.shape[1])), (0, 1))
    elif kind == "scale":
        s = 1 + rng.uniform(-amount, amount)
        g = g[np.clip((np.arange(g.shape[0]) / s).astype(int), 0, g.shape[0] - 1)][:, np.clip((np.arange(g.shape[1]) / s).astype(int), 0, g.shape[1] - 1)]
    elif kind == "jitter":
        g = g * (1 + rng.uniform(-amount, amount))
    else:
        raise ValueError(kind)
    return np.clip(np.round(g), 0, 255).astype(grid.dtype)


def rotations(rows: DataFrame) -> DataFrame:
    """Each upright element four times: turned by ``degrees``, with the correction as target; splits by original."""
    out = rows.withColumn("degrees", F.explode(F.array(*[F.lit(d) for d in (0, 90, 180, 270)])))
    return out.withColumn("target", (360 - F.col("degrees")) % 360).withColumn("split", split_of("id"))


def orientation_scores(rows: DataFrame, text: str = "text", side: int = 24) -> DataFrame:
    """``rows`` (with degrees) and ``scores``: four probabilities for the corrections 0, 90, 180, 270.

    A text's raster ends in its last lines, so ink lies in rows from the top left: the evidence is how much more
    alike neighbours are along rows than along columns, and on which end the weight lies.
    """
    from .fingerprints import text_grid

    def run(batches):
        for batch in batches:
            out = []
            for t, d in zip(batch.column(batch.schema.names.index(text)).to_pylist(), batch.column(batch.schema.names.index("degrees")).to_pylist()):
                g = rotate(text_grid(t, side), d).astype(float)
                logits = []
                for k in (0, 90, 180, 270):
                    u = rotate(g, k)
                    half = side // 2
                    logits.append((np.abs(np.diff(u, axis=0)).mean() - np.abs(np.diff(u, axis=1)).mean() + (u[:half].mean() - u[half:].mean())) / 8)
                e = np.exp(np.array(logits) - max(logits))
                out.append((e / e.sum()).tolist())
            yield pa.RecordBatch.from_arrays([*batch.columns, pa.array(out, pa.list_(pa.float64()))], names=[*batch.schema.names, "scores"])

    schema = ", ".join([*(f"`{f.name}` {f.dataType.simpleString()}" for f in rows.schema.fields), "scores array<double>"])
    return rows.mapInArrow(run, schema)


def gated(scores, least: float = 0.99):
    """The correction to apply: that of the best score if it is at least ``least``, else none."""
    best = F.array_max(scores)
    return F.when(best >= least, (F.array_position(scores, best).cast("int") - 1) * 90).otherwise(0)


# ---- captions


def caption_eligible(raw):
    return ~raw.isin("decorative", "artifact")


def extractive_caption(text, words: int = 50):
    """The first words of a text; null where there is none."""
    w = F.filter(F.split(F.coalesce(text, F.lit("")), r"\s+"), lambda x: x != "")
    return F.when(F.size(w) > 0, F.array_join(F.slice(w, 1, words), " "))


def finalize_caption(eligible, response):
    blank = response.isNull() | (F.trim(response) == "")
    return F.when(eligible, F.when(blank, CAPTION_FAILED).otherwise(response))


def run_captions(requests: DataFrame, provider, concurrent: int = 8, timeout: float = 20.0, retries: int = 2) -> DataFrame:
    """``requests`` with ``response`` from ``provider(request) -> str``: one provider a partition, threads inside,
    a timeout and retries for each call; a call that never succeeds leaves null. No provider is called by default."""

    def run(frames):
        from concurrent.futures import ThreadPoolExecutor
        from concurrent.futures import TimeoutError as Late

        with ThreadPoolExecutor(concurrent) as pool:
            def call(request):
                for _ in range(retries + 1):
                    try:
                        return provider(request)
                    except Exception:  # noqa: BLE001 a failed call is a result of its own
                        continue
                return None

            for f in frames:
                waiting = [pool.submit(call, r) for r in f["request"]]
                got = []
                for w in waiting:
                    try:
                        got.append(w.result(timeout))
                    except Late:
                        got.append(None)
                yield f.assign(response=pd.Series(got, index=f.index, dtype=object))

    schema = ", ".join([*(f"`{x.name}` {x.dataType.simpleString()}" for x in requests.schema.fields), "response string"])
    return requests.mapInPandas(run, schema)


def thesaurus_matches(rows: DataFrame, terms: DataFrame, key: str = "doc_id", text: str = "text") -> DataFrame:
    """(key, keyword, surface, n): exact, case-sensitive occurrences of surface forms among the words of a text."""
    word = F.explode(F.regexp_extract_all(text, F.lit(r"[\p{L}\p{N}]+"), F.lit(0)))
    words = rows.select(key, word.alias("surface"))
    return words.join(terms, "surface").groupBy(key, "keyword", "surface").agg(F.count("*").alias("n"))


def nested_matches(flat: DataFrame, key: str = "doc_id") -> DataFrame:
    """(key, matches): map of keyword to a map of surface form to count."""
    inner = flat.groupBy(key, "keyword").agg(F.map_from_entries(F.collect_list(F.struct("surface", "n"))).alias("m"))
    return inner.groupBy(key).agg(F.map_from_entries(F.collect_list(F.struct("keyword", "m"))).alias("matches"))
