import struct
import zlib

import numpy as np
from pyspark.sql import functions as F

from figmine.operators import dedup, elements, scans


def png(grid):
    h, w = grid.shape
    chunk = lambda kind, body: struct.pack(">I", len(body)) + kind + body + struct.pack(">I", zlib.crc32(kind + body))
    lines = b"".join(b"\0" + row.tobytes() for row in grid)
    return b"\x89PNG\r\n\x1a\n" + chunk(b"IHDR", struct.pack(">IIBBBBB", w, h, 8, 0, 0, 0, 0)) + chunk(b"IDAT", zlib.compress(lines)) + chunk(b"IEND", b"")


def drawn(h, w, *boxes):
    grid = np.full((h, w), 255, np.uint8)
    for x0, y0, x1, y1 in boxes:
        grid[y0:y1, x0:x1] = 10
    return grid


def test_reading_scans(spark, tmp_path):
    grid = drawn(30, 40, (5, 5, 20, 12), (8, 18, 30, 27))
    (tmp_path / "deep").mkdir()
    (tmp_path / "deep" / "a.png").write_bytes(png(grid))
    (tmp_path / "broken.png").write_bytes(b"no image")
    (tmp_path / "b.pgm").write_bytes(b"P5\n# made here\n40 30\n255\n" + grid.tobytes())
    (tmp_path / "c.ppm").write_bytes(b"P6 1 1 255 " + bytes([255, 0, 0]))
    (tmp_path / "short.pgm").write_bytes(b"P5 9 9 255 x")
    images = {r["origin"].rsplit("/", 1)[1]: r["grid"] for r in scans.read_scans(spark, str(tmp_path), pattern="*.png").collect()}
    assert images["broken.png"] is None and (scans.unpacked(images["a.png"]) == grid).all()
    maps = {r["origin"].rsplit("/", 1)[1]: r["grid"] for r in scans.read_scans(spark, str(tmp_path), scans.decode_pnm, "*.p?m").collect()}
    assert maps["short.pgm"] is None and (scans.unpacked(maps["b.pgm"]) == grid).all()
    assert scans.unpacked(maps["c.ppm"]).tolist() == [[255 * 299 // 1000]]


def test_whitespace_detection(spark, tmp_path):
    found = scans.WhitespaceScorer()(drawn(40, 40, (3, 3, 20, 10), (25, 3, 36, 10), (3, 20, 36, 36)))
    assert [b[:4] for b in found] == [(3, 3, 20, 10), (25, 3, 36, 10), (3, 20, 36, 36)]
    assert all(0.3 <= b[4] <= 1 for b in found)
    assert scans.WhitespaceScorer()(drawn(5, 5)) == []
    # a box at the very edge has no margin
    assert scans.WhitespaceScorer()(drawn(9, 9, (0, 0, 4, 4)))[0][4] == 0
    boxes = spark.createDataFrame([(1, 0, "article", 950), (1, 1, "nav", 40), (2, 0, "ul", 101)], "page_id int, block_no int, tag string, size int")
    placed = scans.layout(boxes)
    assert sorted(map(tuple, placed.select("page_id", "block_no", "x0", "y0", "x1", "y1").collect())) == [(1, 0, 40, 24, 760, 184), (1, 1, 40, 208, 280, 224), (2, 0, 40, 24, 280, 56)]
    pages = scans.render(placed)
    truth = placed.select("page_id", F.concat_ws("-", "page_id", "block_no").alias("id"), *[F.floor(F.col(c) / 8).cast("double").alias(c) for c in ("x0", "y0", "x1", "y1")])
    assert elements.match_boxes(scans.detect(pages), truth, "page_id").first()["recall"] == 1
    nothing = spark.createDataFrame([(1, None)], f"page_id int, grid {scans.GRID}")
    assert scans.detect(nothing).count() == 0 and scans.detect(nothing.limit(0)).count() == 0


def test_probed_bands_find_what_brute_force_finds(spark):
    rng = np.random.default_rng(3)
    base = [int.from_bytes(rng.bytes(18), "big") for _ in range(12)]
    numbers = base + [b ^ sum(1 << int(k) for k in rng.choice(144, int(rng.integers(1, 17)), replace=False)) for b in base for _ in range(4)]
    rows = spark.createDataFrame([(k, f"{x:036x}") for k, x in enumerate(numbers)] + [(99, None)], "id int, hash string")
    for probes in (0, 1, 2):
        truth = set()
        for a, x in enumerate(numbers):
            for b in range(a + 1, len(numbers)):
                d = x ^ numbers[b]
                if d.bit_count() <= 16 and any(((d >> 24 * k) & 0xFFFFFF).bit_count() <= probes for k in range(6)):
                    truth.add((a, b, d.bit_count()))
        found = list(map(tuple, dedup.probed_edges(rows, probes=probes).collect()))
        assert len(found) == len(set(found)) and set(found) == truth


def test_colour_augmentation():
    rgb = np.random.default_rng(1).integers(0, 256, (8, 9, 3)).astype(np.uint8)
    assert (scans.from_hsv(scans.to_hsv(rgb)) == rgb).all()
    assert scans.to_hsv(np.array([[[255, 0, 0], [0, 255, 0], [7, 7, 7]]], np.uint8))[0, :, 0].round(4).tolist() == [0, 0.3333, 0]
    turned = scans.jitter_hsv(rgb, 5)
    assert (turned == scans.jitter_hsv(rgb, 5)).all() and (turned != rgb).any()
    assert (scans.jitter_hsv(rgb, 5, (0, 0, 0)) == rgb).all()
    four = [np.full((3 + k, 5, 3), 50 * k + 1, np.uint8) for k in range(4)]
    out, boxes = scans.mosaic(four, 16, 2)
    for k, (x0, y0, x1, y1) in enumerate(boxes):
        assert (out[y0:y1, x0:x1] == 50 * k + 1).all() and x1 > x0 and y1 > y0
