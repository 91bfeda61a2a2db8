"""Two fingerprints of an element: a bit hash and a dense vector."""

from __future__ import annotations

import hashlib
import math
import re
import zlib
from collections import Counter

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

_SPACE = re.compile(r"\s+")


def _grams(text: str | None, n: int) -> list[str]:
    words = [w for w in _SPACE.split((text or "").lower()) if w]
    if not words:
        return []
    return list({" ".join(words[k : k + n]) for k in range(max(1, len(words) - n + 1))})


def _digests(grams: list[str], size: int) -> np.ndarray:
    """``size`` bytes of each n-gram's salted md5 digests, as a matrix."""
    raw = []
    for g in grams:
        one = hashlib.md5(g.encode()).digest()
        salt = 1
        while len(one) < size:
            one += hashlib.md5(f"{g}#{salt}".encode()).digest()
            salt += 1
        raw.append(one[:size])
    return np.frombuffer(b"".join(raw), np.uint8).reshape(len(grams), size)


def _sign_of(digests: np.ndarray, bits: int) -> str:
    votes = np.unpackbits(digests, axis=1)[:, :bits].sum(axis=0, dtype=np.int64)
    return np.packbits(2 * votes > len(digests)).tobytes().hex()[: bits // 4]


def sign_hash(rows: DataFrame, text: str = "text", bits: int = 144, n: int = 3) -> DataFrame:
    """``rows`` with ``hash``: hex digits of a sign hash over the set of word n-grams; null without a word.

    A bit is set where more than half of the n-grams' digests have it set. One pass, no shuffle.
    """

    def run(batches):
        for batch in batches:
            out = []
            for t in batch.column(batch.schema.names.index(text)).to_pylist():
                grams = _grams(t, n)
                out.append(_sign_of(_digests(grams, -(-bits // 8)), bits) if grams else None)
            yield pa.RecordBatch.from_arrays([*batch.columns, pa.array(out, pa.string())], names=[*batch.schema.names, "hash"])

    return spread(rows).mapInArrow(run, _schema(rows, "hash string"))


def sign_bytes(text: str | None, bits: int, n: int = 3) -> bytes | None:
    """The hash of ``sign_hash`` as bytes."""
    grams = _grams(text, n)
    return bytes.fromhex(_sign_of(_digests(grams, -(-bits // 8)), bits)) if grams else None


def fingerprint(rows: DataFrame, text: str = "text", key: str = "id", bits: int = 144, n: int = 3, width: int = 512) -> DataFrame:
    """(key, hash, vec): the sign hash and the dense vector of one set of word n-grams, whose digests are taken once."""

    def run(batches):
        for batch in batches:
            hashes, vectors = [], []
            for t in batch.column(1).to_pylist():
                grams = _grams(t, n)
                digests = _digests(grams, -(-bits // 8)) if grams else None
                hashes.append(_sign_of(digests, bits) if grams else None)
                vectors.append(_unit(_signed_counts(digests, width)) if grams else None)
            yield pa.RecordBatch.from_arrays([batch.column(0), pa.array(hashes, pa.string()), pa.array([None if v is None else v.tolist() for v in vectors], pa.list_(pa.float64()))], names=[key, "hash", "vec"])

    return spread(rows.select(key, text)).mapInArrow(run, f"`{key}` {rows.schema[key].dataType.simpleString()}, hash string, vec array<double>")


def spread(rows: DataFrame) -> DataFrame:
    """``rows`` over all cores where the files give fewer parts than there are, as a single small file does; else as they are."""
    cores = rows.sparkSession.sparkContext.defaultParallelism
    return rows.repartition(cores) if rows.rdd.getNumPartitions() < cores else rows


def kept(df: DataFrame) -> DataFrame:
    """``df`` written once into the shared checkpoint folder: what follows reads it and does not compute it again."""
    from .graph import ensure_checkpoint_dir

    ensure_checkpoint_dir(df.sparkSession)
    return df.checkpoint()


def packed(rows: DataFrame) -> DataFrame:
    """``rows`` with ``packed`` in place of ``vec``: the same numbers, compressed."""

    def run(batches):
        for batch in batches:
            at = batch.schema.names.index("vec")
            out = [None if v is None else zlib.compress(np.array(v, np.float64).tobytes(), 1) for v in batch.column(at).to_pylist()]
            names = [n for n in batch.schema.names if n != "vec"]
            yield pa.RecordBatch.from_arrays([*(batch.column(n) for n in names), pa.array(out, pa.binary())], names=[*names, "packed"])

    return rows.mapInArrow(run, _schema(rows.drop("vec"), "packed binary"))


def numbers(one: bytes) -> np.ndarray:
    return np.frombuffer(zlib.decompress(one), np.float64)


def unpacked(column):
    """The vector of a ``packed`` column, array<double>."""

    @F.arrow_udf("array<double>")
    def read(values: pa.Array) -> pa.Array:
        return pa.array([None if v is None else numbers(v) for v in values.to_pylist()], pa.list_(pa.float64()))

    return read(column)


def sign_hash_sql(rows: DataFrame, key: str, text: str = "text") -> DataFrame:
    """(key, hash) of the 144-bit hash in DataFrame functions alone: the reference form, 36 rows a gram."""
    words = F.filter(F.split(F.lower(text), r"\s+"), lambda w: w != "")
    count = F.size(words)
    grams = F.array_distinct(F.transform(F.sequence(F.lit(1), F.greatest(count - 2, F.lit(1))), lambda i: F.array_join(F.slice(words, i, 3), " ")))
    g = rows.where(count > 0).select(key, F.explode(grams).alias("gram"))
    digest = F.concat(F.md5("gram"), F.substring(F.md5(F.concat("gram", F.lit("#1"))), 1, 4))
    digits = g.select(key, F.posexplode(F.transform(F.sequence(F.lit(1), F.lit(36)), lambda i: F.conv(F.substring(digest, i, 1), 16, 10).cast("int"))).alias("place", "digit"))
    bit = [F.when(2 * F.sum(F.shiftright("digit", 3 - b).bitwiseAND(1)) > F.count("*"), 1 << (3 - b)).otherwise(0) for b in range(4)]
    folded = digits.groupBy(key, "place").agg(sum(bit[1:], bit[0]).alias("digit"))
    hexed = folded.groupBy(key).agg(F.array_sort(F.collect_list(F.struct("place", F.lower(F.hex("digit")).alias("d")))).alias("s"))
    return hexed.select(key, F.array_join(F.transform("s", lambda x: x["d"]), "").alias("hash"))


def _schema(rows: DataFrame, extra: str) -> str:
    return ", ".join([*(f"`{f.name}` {f.dataType.simpleString()}" for f in rows.schema.fields), extra])


def text_grid(text: str | None, side: int) -> np.ndarray:
    """A text as a square of intensities: each cell the mean code point, modulo 256, of its slice."""
    codes = np.frombuffer((text or "").encode("utf-32-le"), np.uint32).astype(np.int64)
    cells = side * side
    cuts = np.arange(cells + 1) * len(codes) // cells
    total = np.concatenate([[0], np.cumsum(codes)])
    width = np.diff(cuts)
    return np.where(width > 0, (total[cuts[1:]] - total[cuts[:-1]]) // np.maximum(width, 1) % 256, 0).reshape(side, side)


def cosine_basis(side: int, width: int) -> np.ndarray:
    """Integer cosine basis: rows are frequencies."""
    k, n = np.arange(side)[:, None], np.arange(width)[None, :]
    return np.round(1000 * np.cos(math.pi * (2 * n + 1) * k / (2 * width))).astype(np.int64)


def dct_bits(grid: np.ndarray, side: int = 12) -> np.ndarray:
    """Bits of the low block of a two-dimensional cosine transform that lie above the block's median."""
    c = cosine_basis(side, grid.shape[0])
    block = (c @ grid.astype(np.int64) @ c.T).ravel()
    ordered = np.sort(block)
    return 2 * block > ordered[(len(block) - 1) // 2] + ordered[len(block) // 2]


def dct_hash(rows: DataFrame, text: str = "text", side: int = 12) -> DataFrame:
    """``rows`` with ``hash`` over the text's raster of 4 * side cells a side."""

    def run(batches):
        for batch in batches:
            out = [np.packbits(dct_bits(text_grid(t, 4 * side), side)).tobytes().hex()[: side * side // 4] for t in batch.column(batch.schema.names.index(text)).to_pylist()]
            yield pa.RecordBatch.from_arrays([*batch.columns, pa.array(out, pa.string())], names=[*batch.schema.names, "hash"])

    return rows.mapInArrow(run, _schema(rows, "hash string"))


#: name -> (kind of unit, n, width) of the built-in encoders; the first is the copy-detection stand-in.
ENCODERS = {"word3": ("word", 3, 512), "word1": ("word", 1, 512), "char3": ("char", 3, 512), "char1": ("char", 1, 128)}


def encode(text: str | None, kind: str, n: int, width: int) -> np.ndarray | None:
    """Signed counts of hashed n-grams, to unit length; null for nothing to count."""
    if kind == "word":
        grams = _grams(text, n)
    else:
        t = (text or "").lower()
        grams = [t[k : k + n] for k in range(len(t) - n + 1)]
    return _unit(_signed_counts(_digests(grams, 16), width)) if grams else None


def _signed_counts(digests: np.ndarray, width: int) -> np.ndarray:
    place = digests[:, :4].astype(np.int64) @ np.array([1 << 24, 1 << 16, 1 << 8, 1]) % width
    return np.bincount(place, np.where(digests[:, 4] >= 0x80, 1.0, -1.0), minlength=width)


def counts(text: str | None, kind: str, n: int, width: int, seen: dict) -> np.ndarray | None:
    """The signed counts of ``encode`` as whole numbers, null as there. ``seen`` keeps digests of n-grams that come again."""
    if kind == "word":
        grams = dict.fromkeys(_grams(text, n), 1)
    else:
        t = (text or "").lower()
        grams = Counter(t[k : k + n] for k in range(len(t) - n + 1))
    if not grams:
        return None
    marks = np.empty(len(grams), np.int64)
    for k, g in enumerate(grams):
        mark = seen.get(g)
        if mark is None:
            one = hashlib.md5(g.encode()).digest()
            mark = int.from_bytes(one[:5], "big")
            # longer n-grams of words seldom come again
            if (kind == "char" or n == 1) and len(seen) < 1 << 18:
                seen[g] = mark
        marks[k] = mark
    times = np.fromiter(grams.values(), np.int64, len(grams))
    v = np.bincount((marks >> 8) % width, np.where(marks & 0x80, times, -times), minlength=width).astype(np.int32)
    return v if v.any() else None


def _unit(v: np.ndarray) -> np.ndarray | None:
    size = float(np.sqrt(v @ v))
    return v / size if size else None


def embed(rows: DataFrame, text: str = "text", encoder: str = "word3") -> DataFrame:
    """``rows`` with ``vec``, array<double> of unit length or null."""
    kind, n, width = ENCODERS[encoder]

    def run(batches):
        for batch in batches:
            vectors = [encode(t, kind, n, width) for t in batch.column(batch.schema.names.index(text)).to_pylist()]
            yield pa.RecordBatch.from_arrays([*batch.columns, pa.array([None if v is None else v.tolist() for v in vectors], pa.list_(pa.float64()))], names=[*batch.schema.names, "vec"])

    return spread(rows).mapInArrow(run, _schema(rows, "vec array<double>"))
