"""Thresholds and sizes of the whole chain, in one place."""

from __future__ import annotations

from dataclasses import dataclass


@dataclass(frozen=True)
class PipelineConfig:
    # fixed values: the published settings of the chain
    detect_confidence: float = 0.30
    nms_iou: float = 0.20
    keep_confidence: float = 0.75
    class_confidence: float = 0.70
    music_confidence: float = 0.99
    hash_side: int = 12
    bands: int = 6
    band_bits: int = 24
    hamming: int = 16
    similarity: float = 0.86
    neighbours: int = 30
    index_links: int = 12
    index_build_list: int = 100
    index_search_list: int = 30
    orient_confidence: float = 0.99
    caption_words: int = 50
    coverage_minimum: int = 10
    volumes_per_batch: int = 1000
    splits: tuple = (0.8, 0.1, 0.1)


DEFAULT = PipelineConfig()
CLASSES = ("illustration", "artifact", "decorative", "chart", "music")
CAPTION_FAILED = "CAPTION FAILED"
