"""Language-model scoring from a log-frequency Bloom filter.

Training counts every token and every pair of tokens of the training texts. A count c is kept only as its level
1 + floor(log2 c): the filter holds the keys (gram, 1) ... (gram, level), so a reader probes level after level until a
probe misses and the number of hits gives the count back as 1.5 * 2^(level - 1), or 0. An error of the filter can
only raise a level. Probabilities are back-off smoothed: a pair that is held takes 0.9 of count(pair) / count(first),
otherwise 0.1 (or all, at the start of a text or after an unheld token) of the token's add-one share.

The filter's size follows the number of distinct grams (``BITS_PER_KEY`` bits a key); it is cut into shards by hash,
each built by one group of rows and broadcast after a check of its size. Shards that together exceed ``HELD_BYTES``
are searched in several passes, one after the other, which hand their levels on as written columns. The exact token counts of the
base score travel the same way, as sorted tables. Everything counts all training texts.

Nulls and edge cases: a null or empty text is one end token; rows with a null id train the model and are not held out;
repeated rows count and are scored each; an empty table gives an empty result; extra columns pass
through, and one named like a result column is replaced by it.
"""

from __future__ import annotations

import math

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from . import textvec as V
from .common import bounded_batches, free_names, remainder, stored

BITS_PER_KEY = 12
PROBES = 4
#: Distinct grams in a shard, aimed at; a shard of 1 million grams is about 2 MB of filter or 16 MB of exact counts.
SHARD_GRAMS = 1_000_000
#: Bytes of shards that one pass holds.
HELD_BYTES = 400 << 20
RESULT = ("n_tokens", "n_known", "base_score", "score")
END = np.uint64(0x5851F42D4C957F2D)
#: Tokens that a worker holds before it passes partial counts on.
COUNTED_BATCH = 1 << 20
SENT_BYTES = 1 << 20
#: Bytes of text scored together.
SCORED_BYTES = 1 << 19


def _tokens(step: V.Step) -> tuple[np.ndarray, np.ndarray]:
    """Hashes of the tokens of all texts, an end after each, and each text's first token."""
    start, end, first = step.words(V.SPACES)
    n = len(first) - 1
    out = np.full(len(start) + n, END, np.uint64)
    own = np.repeat(np.arange(n), np.diff(first))
    out[np.arange(len(start)) + own] = step.span_hash(start, end)
    return out, first + np.arange(n + 1)


def _pairs(tokens: np.ndarray, first: np.ndarray) -> np.ndarray:
    """Hash of each token with the one before it; 0 at the start of a text."""
    out = np.zeros(len(tokens), np.uint64)
    if len(tokens) > 1:
        out[1:] = V.mix(tokens[:-1] * np.uint64(3) + tokens[1:] + np.uint64(1))
    out[first[:-1]] = 0
    return out


def _shard_of(h: np.ndarray, shards: int) -> np.ndarray:
    return ((h >> np.uint64(40)) % np.uint64(shards)).astype(np.int32)


def _count(shards: int):
    """Packed partial counts: (kind, shard, grams, counts), kind 1 for tokens and 2 for pairs."""

    def pack(parts, kind):
        h, c = np.unique(np.concatenate(parts), return_counts=True)
        shard = _shard_of(h, shards)
        order = np.argsort(shard, kind="stable")
        cuts = np.searchsorted(shard[order], np.arange(shards + 1))
        for k in range(shards):
            own = order[cuts[k] : cuts[k + 1]]
            if len(own):
                yield kind, k, h[own], c[own]

    def run(batches):
        held: dict[int, list] = {1: [], 2: []}
        size = 0

        def flush():
            """Record batches of about ``SENT_BYTES``: a batch is one buffer outside the heap of the executor."""
            rows, sent = [], 0
            for kind in (1, 2):
                parts, held[kind] = held[kind], []
                for _, shard, h, c in pack(parts, kind) if parts else ():
                    # pairs travel as 40 bits, which the filter's own error rate dwarfs; tokens whole
                    rows.append((kind, shard, h.tobytes() if kind == 1 else _narrow(h), _small(c)))
                    sent += len(rows[-1][2]) + len(rows[-1][3])
                    if sent > SENT_BYTES:
                        yield _batch(rows)
                        rows, sent = [], 0
            if rows:
                yield _batch(rows)

        for batch in batches:
            for _, step in V.steps(batch.column(0)):
                tokens, first = _tokens(step)
                pairs = _pairs(tokens, first)
                held[1].append(tokens)
                held[2].append(pairs[pairs != 0])
                size += len(tokens)
                if size >= COUNTED_BATCH:
                    yield from flush()
                    size = 0
        if size:
            yield from flush()

    return run


def _batch(rows: list) -> pa.RecordBatch:
    kinds = (pa.int32(), pa.int32(), pa.binary(), pa.binary())
    return pa.RecordBatch.from_arrays([pa.array(x, t) for x, t in zip(zip(*rows), kinds)], names=["kind", "shard", "grams", "counts"])


def _narrow(h: np.ndarray) -> bytes:
    return np.ascontiguousarray(h.view(np.uint8).reshape(-1, 8)[:, :5]).tobytes()


def _wide(raw: bytes) -> np.ndarray:
    out = np.zeros((len(raw) // 5, 8), np.uint8)
    out[:, :5] = np.frombuffer(raw, np.uint8).reshape(-1, 5)
    return out.view(np.uint64).ravel()


_WIDTHS = {1: np.uint8, 4: np.uint32, 8: np.uint64}


def _small(c: np.ndarray) -> bytes:
    """Counts in the narrowest width that holds them all, after a byte that names it."""
    most = int(c.max(initial=0))
    width = 1 if most < 1 << 8 else 4 if most < 1 << 32 else 8
    return bytes([width]) + c.astype(_WIDTHS[width]).tobytes()


def _counts(raw: bytes) -> np.ndarray:
    """What ``_small`` wrote, as it lies there."""
    return np.frombuffer(raw, _WIDTHS[raw[0]], offset=1)


def _bits(h: np.ndarray, level: int, size: int):
    a = V.mix(h + np.uint64(level * 0xD6E8FEB86659FD93 & 0xFFFFFFFFFFFFFFFF))
    b = (a >> np.uint64(32)) | np.uint64(1)
    for k in range(PROBES):
        yield (a + np.uint64(k) * b) % np.uint64(size)


def _levels_of(counts: np.ndarray) -> np.ndarray:
    return 1 + np.floor(np.log2(np.maximum(counts, 1))).astype(np.int64)


class BloomShard:
    def __init__(self, bits: np.ndarray):
        self.bits, self.size = bits, len(bits) * 8

    @staticmethod
    def build(grams: np.ndarray, counts: np.ndarray) -> BloomShard:
        levels = _levels_of(counts)
        size = -(-max(64, int(levels.sum()) * BITS_PER_KEY) // 8) * 8
        out = np.zeros(size, bool)
        for level in range(1, int(levels.max(initial=0)) + 1):
            for at in _bits(grams[levels >= level], level, size):
                out[at] = True
        return BloomShard(np.packbits(out, bitorder="little"))


class Filters:
    """The filters of many shards as one string of bits, so that a probe serves grams of all shards at once."""

    def __init__(self, shards: int):
        self.base, self.size = np.zeros(shards, np.uint64), np.zeros(shards, np.uint64)
        self.raw = bytearray()

    def add(self, shard: int, bits: bytes) -> None:
        self.base[shard], self.size[shard] = 8 * len(self.raw), 8 * len(bits)
        self.raw += bits

    def levels(self, grams: np.ndarray, shard: np.ndarray) -> np.ndarray:
        """Level of each gram, by probing until a miss; 0 for the shards that are not here."""
        out = np.zeros(len(grams), np.int8)
        live = np.flatnonzero(self.size[shard])
        bits = np.frombuffer(self.raw, np.uint8) if len(live) else None
        level = 1
        while len(live) and level < 64:
            base = self.base[shard[live]]
            hit = np.ones(len(live), bool)
            for at in _bits(grams[live], level, self.size[shard[live]]):
                at += base
                hit &= (bits[at >> np.uint64(3)] >> (at & np.uint64(7)).astype(np.uint8)) & 1 > 0
            live = live[hit]
            out[live] = level
            level += 1
        return out


def _build(key, table):
    """One shard of one kind: the exact table of tokens with its filter, or the filter of the pairs."""
    kind = key[0].as_py()
    raw = table.column("grams").to_pylist()
    grams = np.concatenate([np.frombuffer(r, np.uint64) if kind == 1 else _wide(r) for r in raw])
    counts = np.concatenate([_counts(c) for c in table.column("counts").to_pylist()])
    grams, inverse = np.unique(grams, return_inverse=True)
    counts = np.bincount(inverse, weights=counts, minlength=len(grams)).astype(np.int64)
    shard = BloomShard.build(grams & np.uint64((1 << 40) - 1), counts)
    exact = kind == 1
    return pa.table(
        {
            "kind": pa.array([kind], pa.int32()),
            "shard": pa.array([key[1].as_py()], pa.int32()),
            "distinct_grams": pa.array([len(grams)], pa.int64()),
            "total": pa.array([int(counts.sum())], pa.int64()),
            "bits": pa.array([shard.bits.tobytes()], pa.binary()),
            "grams": pa.array([grams.tobytes() if exact else b""], pa.binary()),
            "counts": pa.array([_small(counts) if exact else b""], pa.binary()),
        }
    )


class Model:
    """The written shards of both kinds, which of them each pass reads, and the totals."""

    def __init__(self, built: DataFrame, passes: list[list], shards: int, total: int, vocabulary: int):
        self.built, self.passes, self.shards, self.total, self.vocabulary = built, passes, shards, total, vocabulary

    def held(self, k: int) -> list:
        """Broadcasts of the shards of pass k, none larger than a shard and all of them together than a pass may hold."""
        sc = self.built.sparkSession.sparkContext
        wanted = [s for _, s in self.passes[k]]
        # one shard at a time passes through the driver
        rows = self.built.where(F.col("shard").between(min(wanted), max(wanted))).orderBy("shard", "kind").toLocalIterator() if wanted else ()
        return [(r["kind"], r["shard"], sc.broadcast((bytes(r["bits"]), bytes(r["grams"]), bytes(r["counts"])))) for r in rows if (r["kind"], r["shard"]) in set(self.passes[k])]


def train(docs: DataFrame, text: str = "text", shard_grams: int = SHARD_GRAMS, held_bytes: int = HELD_BYTES) -> Model:
    # characters bound the number of grams, so the number of shards follows the input
    characters = docs.agg(F.sum(F.length(text)).alias("n")).first()["n"] or 0
    shards = max(1, math.ceil(characters / 6 / shard_grams))
    partial = docs.select(text).mapInArrow(_count(shards), "kind int, shard int, grams binary, counts binary")
    built = stored(partial.groupBy("kind", "shard").applyInArrow(_build, "kind int, shard int, distinct_grams bigint, total bigint, bits binary, grams binary, counts binary"), "op8-shards")
    size = sum(F.octet_length(c).cast("bigint") for c in ("bits", "grams", "counts"))
    # a row of five numbers a shard
    known = built.select("kind", "shard", "total", "distinct_grams", size.alias("size")).orderBy("shard", "kind").collect()
    total, vocabulary = (sum(r[c] for r in known if r["kind"] == 1) for c in ("total", "distinct_grams"))
    passes: list[list] = [[]]
    now = 0
    for r in known:
        if passes[-1] and now + r["size"] > held_bytes:
            passes.append([])
            now = 0
        now += r["size"]
        passes[-1].append((r["kind"], r["shard"]))
    return Model(built, passes, shards, total, vocabulary)


def _lookup(broadcasts: list, shards: int):
    """Fills in, for the shards of this pass, the count and level of each token and the level of each pair."""
    exact = {}
    words, doubles = Filters(shards), Filters(shards)
    for kind, shard, b in broadcasts:
        bits, grams, counts = b.value
        (words if kind == 1 else doubles).add(shard, bits)
        if kind == 1:
            exact[shard] = (np.frombuffer(grams, np.uint64), _counts(counts))
        # a worker would keep the bits a second time; the next task reads them from the executor's file again
        if getattr(b, "_path", None):
            b.__dict__.pop("_value", None)
    low = np.uint64((1 << 40) - 1)

    def fill(tokens, pairs, counts, levels, pair_levels):
        unique, inverse = np.unique(tokens, return_inverse=True)
        shard = _shard_of(unique, shards)
        c, level = np.zeros(len(unique), np.int64), words.levels(unique & low, shard)
        order = np.argsort(shard, kind="stable")
        cuts = np.searchsorted(shard[order], np.arange(shards + 1))
        for k, (grams, held) in exact.items():
            own = order[cuts[k] : cuts[k + 1]]
            at = V.position_of(grams, unique[own])
            c[own[at >= 0]] = held[at[at >= 0]]
        own = np.flatnonzero(pairs)
        pair_levels[own] = np.maximum(pair_levels[own], doubles.levels(pairs[own] & low, _shard_of(pairs[own], shards)))
        np.maximum(counts, c[inverse], out=counts)
        np.maximum(levels, level[inverse], out=levels)

    return fill


def score(docs: DataFrame, model: Model, text: str = "text") -> DataFrame:
    """``docs`` with n_tokens, n_known, base_score and score (log10 probabilities); given columns of such names are
    replaced. What a pass finds is written before the next one begins, so shards of one pass are held at a time."""
    docs = docs.drop(*RESULT)
    state_names = free_names(docs, "_c", "_l", "_p")
    n, v, shards = model.total, model.vocabulary, model.shards

    def one_pass(broadcasts, is_first: bool, is_last: bool):
        def run(batches):
            fill = _lookup(broadcasts, shards)
            for batch in batches:
                names = batch.schema.names
                column = batch.column(names.index(text))
                before = None if is_first else [batch.column(names.index(k)).to_pylist() for k in state_names]
                out: list[list] = [[], [], [], []]
                for row, step in V.steps(column, SCORED_BYTES):
                    tokens, first = _tokens(step)
                    pairs = _pairs(tokens, first)
                    if is_first:
                        state = [np.zeros(len(tokens), np.int64), np.zeros(len(tokens), np.int8), np.zeros(len(tokens), np.int8)]
                    else:
                        rows = range(row, row + len(first) - 1)
                        state = [np.frombuffer(b"".join(col[k] for k in rows), kind).copy() for col, kind in zip(before, (np.int64, np.int8, np.int8))]
                    fill(tokens, pairs, *state)
                    if is_last:
                        for o, x in zip(out, _scores(first, pairs, *state, n, v)):
                            o += x.tolist()
                    else:
                        for o, x in zip(out, state):
                            o += [x[first[k] : first[k + 1]].tobytes() for k in range(len(first) - 1)]
                keep = [k for k in names if k not in state_names]
                columns = [batch.column(names.index(k)) for k in keep]
                if is_last:
                    new = {"n_tokens": pa.array(out[0], pa.int64()), "n_known": pa.array(out[1], pa.int64()), "base_score": pa.array(out[2], pa.float64()), "score": pa.array(out[3], pa.float64())}
                else:
                    new = {k: pa.array(o, pa.binary()) for k, o in zip(state_names, out)}
                yield pa.RecordBatch.from_arrays([*columns, *new.values()], names=[*keep, *new])

        return run

    fields = [f"`{f.name}` {f.dataType.simpleString()}" for f in docs.schema.fields]
    for k in range(len(model.passes)):
        last = k == len(model.passes) - 1
        new = "n_tokens bigint, n_known bigint, base_score double, score double" if last else ", ".join(f"`{c}` binary" for c in state_names)
        held = model.held(k)
        docs = docs.mapInArrow(one_pass(held, k == 0, last), ", ".join([*fields, new]))
        if not last:
            docs = stored(docs, "op8-levels")
            for _, _, b in held:
                b.unpersist()
    return docs


def _scores(first, pairs, counts, levels, pair_levels, n: int, v: int):
    about = np.where(levels > 0, 1.5 * np.exp2(levels.astype(float) - 1), 0)
    about_pair = np.where(pair_levels > 0, 1.5 * np.exp2(pair_levels.astype(float) - 1), 0)
    base = np.log10((counts + 1.0) / (n + 1.0 * (v + 1)))
    # a quantised count can exceed the total it is a part of
    share = np.minimum((about + 1.0) / (n + 1.0 * (v + 1)), 1.0)
    ahead = np.concatenate([[0.0], about[:-1]]) if len(about) else about
    ahead[first[:-1]] = 0
    held = (about_pair > 0) & (ahead > 0)
    ratio = np.minimum(about_pair / np.maximum(ahead, 1), 1.0)
    p = np.where(held, 0.9 * ratio + 0.1 * share, np.where(ahead > 0, 0.1 * share, share))
    n_tokens = np.diff(first)
    return n_tokens, V.per_text_sum((counts > 0).astype(float), first).astype(np.int64), _sums(base, first), _sums(np.log10(np.maximum(p, 1e-300)), first)


def _sums(x: np.ndarray, first: np.ndarray) -> np.ndarray:
    return np.add.reduceat(x, first[:-1]) if len(x) else np.zeros(0)


def op8_log_frequency_bloom_lm(spark, sf_dir: str) -> DataFrame:
    bounded_batches(spark)
    docs = spark.read.parquet(f"{sf_dir}/documents.parquet").select("doc_id", "text")
    held = F.coalesce(remainder("doc_id", 7) == 2, F.lit(False))
    model = train(docs.where(~held))
    return score(docs.withColumn("held_out", held), model).select("doc_id", "held_out", "n_tokens", "n_known", F.lit(model.total).cast("bigint").alias("train_tokens"), "base_score", "score")
