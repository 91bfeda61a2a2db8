"""Page images: reading, region detection by white space, layout of html blocks, colour augmentation.

A grid is struct(h, w, px): gray intensities row by row, 0 black. A file that cannot be read has a null grid, a null grid
has no boxes, and neither stops a job.
"""

from __future__ import annotations

import re

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame, SparkSession, Window
from pyspark.sql import functions as F

from .collection import grayscale

GRID = "struct<h:int,w:int,px:binary>"
_GRID = pa.struct([("h", pa.int32()), ("w", pa.int32()), ("px", pa.binary())])


def _packed(grid: np.ndarray | None):
    return None if grid is None else {"h": grid.shape[0], "w": grid.shape[1], "px": grid.astype(np.uint8).tobytes()}


def unpacked(value: dict) -> np.ndarray:
    return np.frombuffer(value["px"], np.uint8).reshape(value["h"], value["w"])


def decode_pnm(raw: bytes) -> np.ndarray | None:
    """A binary gray or colour map (P5, P6, at most 255) as a gray grid; anything else, or too few bytes, is None."""
    m = re.match(rb"(P[56])(?:\s+|#[^\n]*\n)+(\d+)(?:\s+|#[^\n]*\n)+(\d+)(?:\s+|#[^\n]*\n)+(\d+)\s", raw)
    if not m or not 0 < int(m[4]) < 256:
        return None
    w, h, channels = int(m[2]), int(m[3]), 1 if m[1] == b"P5" else 3
    body = np.frombuffer(raw, np.uint8, offset=m.end())
    if not w * h or len(body) < w * h * channels:
        return None
    body = body[: w * h * channels].reshape(h, w, channels)
    gray = body[:, :, 0] if channels == 1 else grayscale(body)
    return (gray.astype(np.int64) * 255 // int(m[4])).astype(np.uint8)


def read_scans(spark: SparkSession, path: str, decoder=None, pattern: str = "*") -> DataFrame:
    """(origin, grid) of the image files under ``path``, decoded where they are read.

    Without ``decoder`` the built-in image source decodes in the JVM; with one (bytes to a gray array, or None) files
    come as bytes. Only files whose name fits ``pattern`` are listed, in folders of any depth.
    """

    def of_bytes(batches):
        for batch in batches:
            grids = [None if x is None else _packed(decoder(x)) for x in batch.column(1).to_pylist()]
            yield pa.RecordBatch.from_arrays([batch.column(0), pa.array(grids, _GRID)], names=["origin", "grid"])

    def of_pixels(batches):
        for batch in batches:
            grids = []
            for h, w, channels, data in zip(*(batch.column(k).to_pylist() for k in range(1, 5))):
                if h <= 0 or not data:
                    grids.append(None)
                    continue
                px = np.frombuffer(data, np.uint8).reshape(h, w, channels)
                # the source stores blue first
                grids.append(_packed(px[:, :, 0] if channels == 1 else grayscale(px[:, :, 2::-1])))
            yield pa.RecordBatch.from_arrays([batch.column(0), pa.array(grids, _GRID)], names=["origin", "grid"])

    files = spark.read.option("pathGlobFilter", pattern).option("recursiveFileLookup", "true")
    if decoder:
        return files.format("binaryFile").load(path).select(F.col("path").alias("origin"), "content").mapInArrow(of_bytes, f"origin string, grid {GRID}")
    images = files.format("image").option("dropInvalid", "false").load(path)
    return images.select("image.origin", "image.height", "image.width", "image.nChannels", "image.data").mapInArrow(of_pixels, f"origin string, grid {GRID}")


class WhitespaceScorer:
    """Regions as what is left between white gutters: the widest gutter of a region cuts it until none is wide enough.

    Confidence is the white margin around a region, against half a gutter, times the share of its cells that hold ink.
    """

    def __init__(self, gutter: int = 2, dark: int = 128):
        self.gutter, self.dark = gutter, dark

    def __call__(self, grid: np.ndarray) -> list[tuple]:
        """(x0, y0, x1, y1, confidence) by rows, then columns."""
        ink = grid < self.dark
        # the smallest margin so far goes with each region: left, top, right, bottom
        found, todo = [], [(0, 0, ink.shape[1], ink.shape[0], (0, 0, 0, 0))]
        while todo:
            x0, y0, x1, y1, slack = todo.pop()
            part = ink[y0:y1, x0:x1]
            rows, columns = np.flatnonzero(part.any(axis=1)), np.flatnonzero(part.any(axis=0))
            if not len(rows):
                continue
            left, top, right, bottom = x0 + columns[0], y0 + rows[0], x0 + columns[-1] + 1, y0 + rows[-1] + 1
            slack = (slack[0] + left - x0, slack[1] + top - y0, slack[2] + x1 - right, slack[3] + y1 - bottom)
            gaps = [np.diff(rows) - 1, np.diff(columns) - 1]
            widest = [g.max(initial=0) for g in gaps]
            if max(widest) < self.gutter:
                margin = min(slack)
                found.append((int(left), int(top), int(right), int(bottom), float(margin / (margin + self.gutter / 2) * ink[top:bottom, left:right].mean())))
            elif widest[0] >= widest[1]:
                at = int(gaps[0].argmax())
                cut = y0 + (rows[at] + 1 + rows[at + 1]) // 2
                todo += [(left, top, right, cut, (slack[0], slack[1], slack[2], 0)), (left, cut, right, bottom, (slack[0], 0, slack[2], slack[3]))]
            else:
                at = int(gaps[1].argmax())
                cut = x0 + (columns[at] + 1 + columns[at + 1]) // 2
                todo += [(left, top, cut, bottom, (slack[0], slack[1], 0, slack[3])), (cut, top, right, bottom, (0, slack[1], slack[2], slack[3]))]
        return sorted(found, key=lambda b: (b[1], b[0]))


def detect(pages: DataFrame, scorer=None, least: float = 0.30, page: str = "page_id") -> DataFrame:
    """(page, id, x0, y0, x1, y1, confidence) of the regions at or above ``least``. ``scorer`` takes a gray array."""
    scorer = scorer or WhitespaceScorer()
    kind = pages.schema[page].dataType.simpleString()

    def run(batches):
        for batch in batches:
            at, boxes = [], []
            for row, grid in enumerate(batch.column(1).to_pylist()):
                for k, box in enumerate(scorer(unpacked(grid)) if grid and grid["px"] else []):
                    if box[4] >= least:
                        at.append(row)
                        boxes.append((k, *box))
            columns = [batch.column(0).take(pa.array(at, pa.int64())), pa.array([b[0] for b in boxes], pa.int32())]
            columns += [pa.array([float(b[k]) for b in boxes], pa.float64()) for k in range(1, 6)]
            yield pa.RecordBatch.from_arrays(columns, names=[page, "box_no", "x0", "y0", "x1", "y1", "confidence"])

    out = pages.select(page, "grid").mapInArrow(run, f"`{page}` {kind}, box_no int, x0 double, y0 double, x1 double, y1 double, confidence double")
    return out.select(page, F.concat_ws(":", F.col(page).cast("string"), "box_no").alias("id"), "x0", "y0", "x1", "y1", "confidence")


#: Layout of html blocks: left edge, widths of narrow and wide blocks, line height, characters a line, space between.
LEFT, NARROW, WIDE, LINE, PER_LINE, SPACE = 40, 240, 720, 16, 100, 24


def layout(blocks: DataFrame, page: str = "page_id") -> DataFrame:
    """``blocks`` with x0, y0, x1, y1: one column, each block as high as its characters need."""
    height = F.ceil(F.col("size") / PER_LINE) * LINE + SPACE
    above = Window.partitionBy(page).orderBy("block_no").rowsBetween(Window.unboundedPreceding, -1)
    top = F.coalesce(F.sum(height).over(above), F.lit(0)) + SPACE
    width = F.when(F.col("tag").isin("nav", "ul"), NARROW).otherwise(WIDE)
    placed = blocks.withColumn("x0", F.lit(LEFT)).withColumn("y0", top.cast("bigint")).withColumn("x1", F.lit(LEFT) + width)
    return placed.withColumn("y1", (F.col("y0") + height - SPACE).cast("bigint"))


def render(boxes: DataFrame, scale: int = 8, page: str = "page_id") -> DataFrame:
    """(page, grid) of the boxes of each page drawn dark on white, ``scale`` units a cell: pages whose regions are known."""
    shapes = boxes.groupBy(page).agg(F.collect_list(F.struct(*[F.floor(F.col(c) / scale).cast("int").alias(c) for c in ("x0", "y0", "x1", "y1")])).alias("boxes"))
    kind = boxes.schema[page].dataType.simpleString()

    def run(batches):
        for batch in batches:
            grids = []
            for found in batch.column(1).to_pylist():
                grid = np.full((max(b["y1"] for b in found) + 3, (LEFT * 2 + WIDE) // scale), 255, np.uint8)
                for b in found:
                    grid[b["y0"] : b["y1"], b["x0"] : b["x1"]] = 0
                grids.append(_packed(grid))
            yield pa.RecordBatch.from_arrays([batch.column(0), pa.array(grids, _GRID)], names=[page, "grid"])

    return shapes.mapInArrow(run, f"`{page}` {kind}, grid {GRID}")


# ---- augmentation of colour grids


def to_hsv(rgb: np.ndarray) -> np.ndarray:
    """Hue, saturation and value in 0 to 1 of a height x width x 3 grid."""
    c = rgb.astype(float) / 255
    top, low = c.max(axis=2), c.min(axis=2)
    spread = np.where(top > low, top - low, 1)
    r, g, b = c[..., 0], c[..., 1], c[..., 2]
    sector = np.select([top == r, top == g], [(g - b) / spread, 2 + (b - r) / spread], 4 + (r - g) / spread)
    hue = np.where(top > low, sector / 6 % 1, 0)
    return np.stack([hue, np.where(top > 0, (top - low) / np.where(top > 0, top, 1), 0), top], axis=2)


def from_hsv(hsv: np.ndarray) -> np.ndarray:
    h, s, v = hsv[..., 0] * 6, hsv[..., 1], hsv[..., 2]
    out = [v - v * s * np.clip(np.minimum(k, 4 - k), 0, 1) for k in ((n + h) % 6 for n in (5, 3, 1))]
    return np.clip(np.round(np.stack(out, axis=2) * 255), 0, 255).astype(np.uint8)


def jitter_hsv(rgb: np.ndarray, seed: int, amounts=(0.015, 0.7, 0.4)) -> np.ndarray:
    """Hue turned, saturation and value scaled, each by a seeded draw within its amount."""
    draw = np.random.default_rng(seed).uniform(-1, 1, 3) * amounts
    hsv = to_hsv(rgb)
    hsv[..., 0] = (hsv[..., 0] + draw[0]) % 1
    hsv[..., 1:] = np.clip(hsv[..., 1:] * (1 + draw[1:]), 0, 1)
    return from_hsv(hsv)


def mosaic(grids: list[np.ndarray], side: int, seed: int) -> tuple[np.ndarray, list[tuple]]:
    """Four grids around a seeded centre of one square, and the box (x0, y0, x1, y1) that each has there."""
    from .collection import resize

    x, y = (int(v) for v in np.random.default_rng(seed).integers(side // 4, side - side // 4 + 1, 2))
    boxes = [(0, 0, x, y), (x, 0, side, y), (0, y, x, side), (x, y, side, side)]
    out = np.zeros((side, side, *grids[0].shape[2:]), grids[0].dtype)
    for grid, (x0, y0, x1, y1) in zip(grids, boxes):
        out[y0:y1, x0:x1] = resize(grid, y1 - y0, x1 - x0)
    return out, boxes
