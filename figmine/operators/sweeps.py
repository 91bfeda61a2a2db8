"""Fingerprints judged by all pairs of elements against the overlap of their word n-grams, in counts and not in pairs.

Elements with one set of n-grams are one class. True pairs stay pairs of classes, and what a fingerprint scores is counted
tile by tile, so no table of pairs is written.
"""

from __future__ import annotations

import hashlib
import zlib

import numpy as np
import pyarrow as pa
import pyarrow.compute as pc
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from . import dedup
from .fingerprints import kept

#: Sets that tell which n-grams are common. This orders n-grams and decides nothing else.
ORDER_FROM, COMMON = 4000, 1 << 18
#: Elements of a block of the overlap search and of a tile of the scores; rows and columns multiplied at once; steps of pairs.
BLOCK, TILE, ROWS, COLUMNS, STEP = 2048, 16384, 256, 2048, 1 << 20
#: Pairs up to which a tile counts every score, and the share of them it counts beyond that.
WHOLE, SHARE = 1 << 22, 0.005
#: Steps of a cosine.
GRID = 10_000


# ---- classes and true pairs


def word_hashes(text: str = "text"):
    """64-bit hashes of a text's lower-case words."""
    return F.transform(F.filter(F.split(F.lower(text), r"\s+"), lambda w: w != ""), lambda w: F.xxhash64(w))


def _mixed(x: np.ndarray) -> np.ndarray:
    x = (x ^ (x >> np.uint64(30))) * np.uint64(0xBF58476D1CE4E5B9)
    x = (x ^ (x >> np.uint64(27))) * np.uint64(0x94D049BB133111EB)
    return x ^ (x >> np.uint64(31))


def gram_sets(words: pa.Array, n: int = 3) -> list[np.ndarray]:
    """The sorted set of 64-bit n-gram hashes of each row of word hashes; fewer words than ``n`` are one n-gram."""
    words = words.combine_chunks() if isinstance(words, pa.ChunkedArray) else words
    ends = words.offsets.to_numpy()
    flat = words.values.to_numpy(zero_copy_only=False).view(np.uint64)
    out = []
    for k, (lo, hi) in enumerate(zip(ends[:-1], ends[1:])):
        if hi == lo or not words[k].is_valid:
            out.append(np.zeros(0, np.uint64))
            continue
        w = flat[lo:hi]
        size = min(n, len(w))
        one = np.full(len(w) - size + 1, size, np.uint64)
        for at in range(size):
            one = _mixed(one * np.uint64(0x9E3779B97F4A7C15) + w[at : at + len(one)])
        out.append(np.unique(one))
    return out


def class_of(grams: np.ndarray) -> int:
    """The number of a set of n-grams, not 0; 0 for the empty one."""
    return int.from_bytes(hashlib.blake2b(grams.tobytes(), digest_size=8).digest(), "little", signed=True) or 1 if len(grams) else 0


def with_class(rows: DataFrame, text: str = "text") -> DataFrame:
    """``rows`` with ``class``."""

    def run(batches):
        for batch in batches:
            found = [class_of(g) for g in gram_sets(batch.column(batch.num_columns - 1))]
            yield pa.RecordBatch.from_arrays([*batch.columns[:-1], pa.array(found, pa.int64())], names=[*batch.schema.names[:-1], "class"])

    return rows.withColumn("w", word_hashes(text)).mapInArrow(run, ", ".join([*(f"`{f.name}` {f.dataType.simpleString()}" for f in rows.schema.fields), "class bigint"]))


def _met(gram: np.ndarray, owner: np.ndarray, size: np.ndarray, block: np.ndarray, blocks: int, share: float) -> tuple[np.ndarray, np.ndarray]:
    """(tile, owner), each once, of pairs of owners that have an n-gram in common and sizes which allow the overlap.
    ``gram`` is in order; a tile is a pair of blocks."""
    starts = np.flatnonzero(np.append(True, gram[1:] != gram[:-1])[: len(gram)])
    ends = np.repeat(np.append(starts[1:], len(gram)), np.diff(np.append(starts, len(gram))))
    after = ends - np.arange(len(gram)) - 1
    total = np.cumsum(after)
    keys, at = np.zeros(0, np.int64), 0
    while at < len(gram):
        to = max(at + 1, int(np.searchsorted(total, (total[at - 1] if at else 0) + STEP, "right")))
        n = after[at:to]
        x = np.repeat(np.arange(at, to), n)
        y = x + 1 + np.arange(n.sum()) - np.repeat(np.cumsum(n) - n, n)
        x, y = owner[x], owner[y]
        near = np.minimum(size[x], size[y]) >= share * np.maximum(size[x], size[y])
        x, y = x[near], y[near]
        tile = (np.minimum(block[x], block[y]) * blocks + np.maximum(block[x], block[y])) * len(size)
        keys = np.unique(np.concatenate([keys, tile + x, tile + y]))
        at = to
    return keys // max(len(size), 1), keys % max(len(size), 1)


_DEALT = "piece int, gram binary, at binary, number binary, size binary, block binary"


def _deal(sets: list, chosen: list, pieces: int, blocks: int) -> pa.RecordBatch:
    """The ``chosen`` n-grams of (class, n-grams) in ``sets``, one row for each piece of their range."""
    owner = np.repeat(np.arange(len(sets)), [len(c) for c in chosen])
    gram = np.concatenate([*chosen, np.zeros(0, np.uint64)])
    piece = (gram % np.uint64(pieces)).astype(np.int64)
    order = np.argsort(piece, kind="stable")
    cuts = np.searchsorted(piece[order], np.arange(pieces + 1))
    number = np.array([c for c, _ in sets], np.int64)
    size = np.array([len(g) for _, g in sets], np.int32)
    block = np.array([int(_mixed(g[:1])[0] % np.uint64(blocks)) for _, g in sets], np.int32)
    out = []
    for k in range(pieces):
        here = order[cuts[k] : cuts[k + 1]]
        if len(here):
            own, at = np.unique(owner[here], return_inverse=True)
            out.append((k, (gram[here] >> np.uint64(32)).astype(np.uint32).tobytes(), at.astype(np.uint16 if len(own) < 1 << 16 else np.int32).tobytes(), number[own].tobytes(), size[own].tobytes(), block[own].tobytes()))
    cols = list(zip(*out)) if out else [()] * 6
    return pa.RecordBatch.from_arrays([pa.array(cols[0], pa.int32()), *(pa.array(c, pa.binary()) for c in cols[1:])], names=["piece", "gram", "at", "number", "size", "block"])


def _dealt(table: pa.Table) -> tuple:
    """n-gram and owner of each entry, and number, size and block of the owners, of the rows of one piece."""
    gram, owner, number, size, block, n = [], [], [], [], [], 0
    for g, at, c, s, b in zip(*(table.column(x).to_pylist() for x in ("gram", "at", "number", "size", "block"))):
        gram.append(np.frombuffer(g, np.uint32))
        owner.append(np.frombuffer(at, np.uint16 if len(at) == len(g) // 2 else np.int32).astype(np.int64) + n)
        number.append(np.frombuffer(c, np.int64))
        size.append(np.frombuffer(s, np.int32))
        block.append(np.frombuffer(b, np.int32))
        n += len(number[-1])
    number, first, same = np.unique(np.concatenate(number), return_index=True, return_inverse=True)
    return np.concatenate(gram), same[np.concatenate(owner)], number, np.concatenate(size)[first].astype(np.int64), np.concatenate(block)[first].astype(np.int64)


def _once(gram: np.ndarray, owner: np.ndarray) -> tuple[np.ndarray, np.ndarray]:
    """Distinct entries, in order of n-grams."""
    keys = np.unique(gram.astype(np.uint64) << np.uint64(32) | owner.astype(np.uint64))
    return (keys >> np.uint64(32)).astype(np.uint32), (keys & np.uint64(0xFFFFFFFF)).astype(np.int64)


def true_pairs(docs: DataFrame, least: float = 0.5, text: str = "text") -> DataFrame:
    """(a, b): classes whose sets of word 3-grams overlap by ``least`` or more (Jaccard), each pair once; exact.

    A set of which fewer than ``least`` occur in other sets has no such pair. Of the others, two that overlap enough share
    one of the n-grams of their prefixes, the rarest first. Classes that meet in a prefix are dealt to tiles with their
    whole sets, which are compared there.
    """
    words = docs.select(word_hashes(text).alias("w")).where("size(w) > 0")
    n = docs.count()
    blocks = max(1, -(-n // BLOCK))
    pieces = max(docs.sparkSession.sparkContext.defaultParallelism, -(-n // 8000))

    def all_grams(batches):
        for batch in batches:
            sets = list({class_of(g): g for g in gram_sets(batch.column(0))}.items())
            yield _deal(sets, [g for _, g in sets], pieces, 1)

    def again(key, table):
        gram, owner, number, size, _ = _dealt(table)
        gram, owner = _once(gram, owner)
        more = np.append(gram[1:] == gram[:-1], False)[: len(gram)]
        more[1:] |= more[:-1]
        times = np.bincount(owner[more], minlength=len(number))
        return pa.table([pa.array(number[times > 0]), pa.array(size[times > 0]), pa.array(times[times > 0])], names=["class", "size", "times"])

    shared = words.mapInArrow(all_grams, _DEALT).groupBy("piece").applyInArrow(again, "class bigint, size bigint, times bigint")
    shared = shared.groupBy("class").agg(F.max("size").alias("size"), F.sum("times").alias("times")).where(F.col("times") >= least * F.col("size"))
    # which sets are read again: at most 2^20 numbers; a set let through by chance is only compared in vain
    wanted = np.zeros(1 << 20, bool)
    wanted[shared.select(F.pmod("class", F.lit(1 << 20)).alias("k")).distinct().toArrow().column("k").to_numpy()] = True

    def whole(batches):
        for batch in batches:
            sets = {class_of(g): g for g in gram_sets(batch.column(0))}
            sets = {c: g.tobytes() for c, g in sets.items() if wanted[c % (1 << 20)]}
            yield pa.RecordBatch.from_arrays([pa.array(list(sets), pa.int64()), pa.array(list(sets.values()), pa.binary())], names=["class", "grams"])

    sets = kept(words.mapInArrow(whole, "class bigint, grams binary").dropDuplicates(["class"]))
    some = sets.where(F.pmod("class", F.lit(max(1, sets.count() // ORDER_FROM))) == 0)

    def sampled(batches):
        for batch in batches:
            yield pa.RecordBatch.from_arrays([pa.array(np.frombuffer(b"".join(batch.column(0).to_pylist()), np.int64))], names=["g"])

    counted = some.select("grams").mapInArrow(sampled, "g bigint").groupBy("g").count().where("count > 2").orderBy(F.desc("count"), "g").limit(COMMON).toArrow()
    common = counted.column("g").to_numpy().view(np.uint64)
    often = counted.column("count").to_numpy()[np.argsort(common)]
    common = np.sort(common)

    def frequency(grams):
        at = np.minimum(np.searchsorted(common, grams), max(len(common) - 1, 0))
        return np.where(common[at] == grams, often[at], 0) if len(common) else np.zeros(len(grams), np.int64)

    def prefixes(batches):
        for batch in batches:
            rows = [(c, np.frombuffer(g, np.uint64)) for c, g in zip(*(batch.column(k).to_pylist() for k in (0, 1)))]
            # of a set, least * its size at least must be common to both
            yield _deal(rows, [g[np.argsort(frequency(g), kind="stable")[: len(g) - int(np.ceil(least * len(g) - 1e-9)) + 1]] for _, g in rows], pieces, blocks)

    def meet(key, table):
        gram, owner, number, size, block = _dealt(table)
        tile, own = _met(*_once(gram, owner), size, block, blocks, least)
        return pa.table([pa.array(tile // blocks), pa.array(tile % blocks), pa.array(number[own]), pa.array(block[own])], names=["i", "j", "class", "block"])

    found = sets.mapInArrow(prefixes, _DEALT).groupBy("piece").applyInArrow(meet, "i bigint, j bigint, class bigint, block bigint").distinct()

    def overlap(key, table):
        left, right = table.filter(pc.equal(table.column("block"), key[0])), table.filter(pc.equal(table.column("block"), key[1]))
        one = key[0].as_py() == key[1].as_py()
        sets = [[np.frombuffer(g, np.uint64) for g in side.column("grams").to_pylist()] for side in ([left] if one else [left, right])]
        number = [side.column("class").to_numpy() for side in ([left] if one else [left, right])]
        size = [np.array([len(g) for g in side]) for side in sets]
        grams = [np.concatenate([*side, np.zeros(0, np.uint64)]) for side in sets]
        values, counts = np.unique(np.concatenate(grams), return_counts=True)
        values = values[counts > 1]
        places = []
        for side, s in zip(grams, size):
            at = np.searchsorted(values, side)
            hit = (at < len(values)) & (values[np.minimum(at, max(len(values) - 1, 0))] == side if len(values) else False)
            row, at = np.repeat(np.arange(len(s)), s)[hit], at[hit]
            order = np.argsort(at, kind="stable")
            places.append((row[order], at[order]))
        rows, others = places[0], places[-1]
        out = [(np.zeros(0, np.int64), np.zeros(0, np.int64))]
        # half a block a side: what is left of the products has a place of several words for each pair
        step = max(1, BLOCK // 2)
        for lo in range(0, len(size[0]), step):
            for low in range(lo if one else 0, len(size[-1]), step):
                n, m = min(step, len(size[0]) - lo), min(step, len(size[-1]) - low)
                both = np.zeros((n, m), np.float32)
                for at in range(0, len(values), 4096):
                    sides = []
                    for (row, place), start, count in ((rows, lo, n), (others, low, m)):
                        a, b = np.searchsorted(place, (at, at + 4096))
                        r, p = row[a:b] - start, place[a:b] - at
                        inside = (r >= 0) & (r < count)
                        x = np.zeros((count, 4096), np.float32)
                        x[r[inside], p[inside]] = 1
                        sides.append(x)
                    both += sides[0] @ sides[1].T
                x, y = np.nonzero(both)
                i = both[x, y].astype(np.int64)
                x, y = x + lo, y + low
                true = i >= least * (size[0][x] + size[-1][y] - i)
                if one:
                    true &= x < y
                out.append((number[0][x[true]], number[-1][y[true]]))
        return pa.table([pa.array(np.concatenate([o[k] for o in out])) for k in (0, 1)], names=["a", "b"])

    return kept(found.join(sets, "class").groupBy("i", "j").applyInArrow(overlap, "a bigint, b bigint"))


# ---- scores of all pairs


class _Bits:
    """Prefixes of one bit hash: the products of a longer one go on from those of the shorter. A score is a distance."""

    def __init__(self, widths):
        self.widths = widths

    def read(self, values):
        """The values as signs, and the product of each with itself."""
        v = np.unpackbits(np.frombuffer(b"".join(values), np.uint8).reshape(len(values), -1), axis=1)[:, : self.widths[-1]].astype(np.float32) * 2 - 1
        return v, np.full(len(v), float(self.widths[-1]))

    def products(self, x, y, sx, sy):
        at, dot = 0, None
        for k, width in enumerate(self.widths):
            more = x[:, at:width] @ y[:, at:width].T
            at, dot = width, more if dot is None else dot + more
            yield k, dot

    def least(self, k, sx, sy, cut):
        return self.widths[k] - 2 * cut

    def score(self, k, dot, sx, sy):
        return ((self.widths[k] - dot) / 2).astype(np.int64)

    def near(self, scores, share):
        """The score that so large a share of the pairs reaches."""
        return int(np.partition(scores, int(len(scores) * share))[int(len(scores) * share)])

    def within(self, score, cut):
        return score <= cut


class _Cosine(_Bits):
    """Counts of one encoder, whole numbers. A score is the cosine in steps of ``GRID``, half a step upwards."""

    def __init__(self):
        super().__init__([0])

    def read(self, values):
        v = np.stack([np.frombuffer(zlib.decompress(one), np.int32) for one in values]).astype(np.float32)
        return v, np.einsum("ij,ij->i", v, v, dtype=np.float64)

    def products(self, x, y, sx, sy):
        # whole numbers: exact in 32 bits where no sum can pass 2^24
        short = sx.max() * sy.max() < 1 << 48
        yield 0, x @ y.T if short else x.astype(np.float64) @ y.astype(np.float64).T

    def least(self, k, sx, sy, cut):
        a, b = np.sqrt(sx) * ((cut - 1) / GRID), np.sqrt(sy)
        return a.astype(np.float32)[:, None] * b.astype(np.float32)

    def score(self, k, dot, sx, sy):
        return np.floor(dot / np.sqrt(sx * sy) * GRID + 0.5).astype(np.int64)

    def near(self, scores, share):
        return -super().near(-scores, share)

    def within(self, score, cut):
        return score >= cut


def bits(*widths: int):
    return _Bits(list(widths))


def cosine():
    return _Cosine()


def score_counts(rows: DataFrame, pairs: DataFrame, kinds: dict, tile: int | None = None, whole: int | None = None) -> DataFrame:
    """(method, score, n, t, cut): how many pairs of rows have a score, and how many of them are true.

    ``rows`` has ``class`` and a binary column for each of ``kinds``, null where there is no fingerprint; ``pairs`` are
    pairs of true classes. Methods are numbered through; method -1 holds the number of true pairs in ``t``. All ``t`` are
    there; each tile leaves out the ``n`` of scores worse than its ``cut``, which it gives in rows without a score.
    """
    tile, limit = tile or TILE, WHOLE if whole is None else whole
    names = list(kinds)
    total = rows.count()
    tiles = max(1, min(-(-total // min(2048, tile)), max(6, -(-total // tile))))
    of = lambda c: F.pmod(F.xxhash64(c), F.lit(tiles))
    ends = [F.least("t", "u").cast("bigint").alias("i"), F.greatest("t", "u").cast("bigint").alias("j")]
    own = F.when(F.col("class") == 0, F.pmod(F.xxhash64(*names), F.lit(tiles))).otherwise(of("class"))
    dealt = rows.withColumn("t", own).withColumn("u", F.explode(F.sequence(F.lit(0), F.lit(tiles - 1)).cast("array<bigint>"))).select("class", *names, "t", *ends)
    true = pairs.withColumns({"t": of("a"), "u": of("b")}).select("a", "b", *ends)

    def run(key, table, links):
        i, j = key[0].as_py(), key[1].as_py()
        one = i == j
        seen: dict = {}
        for row in zip(*(table.column(c).to_pylist() for c in ("t", "class", *names))):
            seen[row] = seen.get(row, 0) + 1
        heads = sorted(seen, key=lambda r: r[:2])
        side, number, members = np.array([r[0] for r in heads], np.int64), np.array([r[1] for r in heads], np.int64), np.array(list(map(seen.get, heads)), np.int64)
        # rows of true pairs
        order = np.argsort(number, kind="stable")
        sorted_ = number[order]
        a, b = (links.column(c).to_numpy() for c in ("a", "b"))
        if one:
            same = np.unique(number[number != 0])
            a, b = np.concatenate([a, same]), np.concatenate([b, same])
        lo, hi = np.searchsorted(sorted_, a), np.searchsorted(sorted_, a, "right")
        pair = np.repeat(np.arange(len(a)), hi - lo)
        x = order[np.arange(len(pair)) - np.repeat(np.cumsum(hi - lo) - (hi - lo), hi - lo) + np.repeat(lo, hi - lo)]
        lo, hi = np.searchsorted(sorted_, b)[pair], np.searchsorted(sorted_, b, "right")[pair]
        ends, at = np.cumsum(hi - lo), 0
        steps = []
        while at < len(x):
            to = max(at + 1, int(np.searchsorted(ends, (ends[at - 1] if at else 0) + STEP // 8, "right")))
            steps.append((at, to))
            at = to

        def linked():
            for at, to in steps:
                n = hi[at:to] - lo[at:to]
                p = np.repeat(x[at:to], n)
                q = order[np.arange(n.sum()) - np.repeat(np.cumsum(n) - n, n) + np.repeat(lo[at:to], n)]
                good = (number[p] != number[q]) | (p < q)
                yield p[good], q[good]
            alone = np.flatnonzero((number != 0) & (members > 1)) if one else np.zeros(0, np.int64)
            yield alone, alone

        def weight(p, q):
            return np.where(p == q, members[p] * (members[p] - 1) // 2, members[p] * members[q])

        out = [(-1, 0, 0, int(sum(weight(p, q).sum() for p, q in linked())), None)]
        base = 0
        for place, (name, kind) in enumerate(kinds.items(), 2):
            valid = np.array([r[place] is not None for r in heads], bool)
            have = np.flatnonzero(valid)
            if not len(have):
                base += len(kind.widths)
                continue
            v, size = kind.read([heads[k][place] for k in have])
            # by length: long ones need 64 bits and are few
            by = np.argsort(size, kind="stable")
            v, size, have = v[by], size[by], have[by]
            back = np.full(len(heads), -1)
            back[have] = np.arange(len(have))
            left, right = np.flatnonzero(side[have] == i), np.flatnonzero(side[have] == j)
            lv, ls = v[left], size[left]
            rv, rs = (lv, ls) if one else (v[right], size[right])
            lm, rm = members[have[left]], members[have[right]]
            cuts: dict = {}
            count: list = [({}, {}) for _ in kind.widths]

            def add(to, score, n):
                if len(score):
                    least = int(score.min())
                    sums = np.bincount(score - least, n)
                    for s in np.flatnonzero(sums).tolist():
                        to[s + least] = to.get(s + least, 0) + int(sums[s])

            if len(left) * len(right) // (2 if one else 1) > limit:
                p, q = np.arange(0, len(left), max(1, len(left) // ROWS)), np.arange(0, len(right), max(1, len(right) // COLUMNS))
                for k, dot in kind.products(lv[p], rv[q], ls[p], rs[q]):
                    score = kind.score(k, dot.ravel().astype(np.float64), np.repeat(ls[p], len(q)), np.tile(rs[q], len(p)))
                    cuts[k] = kind.near(score, SHARE)
                    out.append((base + k, None, None, None, cuts[k]))
            for at in range(0, len(left), ROWS):
                p = slice(at, at + ROWS)
                for low in range(at // COLUMNS * COLUMNS if one else 0, len(right), COLUMNS):
                    q = slice(low, low + COLUMNS)
                    for k, dot in kind.products(lv[p], rv[q], ls[p], rs[q]):
                        if k in cuts:
                            hit = np.flatnonzero((dot >= kind.least(k, ls[p], rs[q], cuts[k])).ravel())
                            a, b = hit // dot.shape[1] + at, hit % dot.shape[1] + low
                            score = kind.score(k, dot.ravel()[hit].astype(np.float64), ls[a], rs[b])
                            good = kind.within(score, cuts[k])
                            if one:
                                good &= a < b
                            add(count[k][0], score[good], lm[a[good]] * rm[b[good]])
                        else:
                            n = lm[p][:, None] * rm[q].astype(np.float64)
                            if one and low < at + ROWS:
                                n *= np.arange(at, at + len(n))[:, None] < np.arange(low, low + n.shape[1])
                            add(count[k][0], kind.score(k, dot.astype(np.float64), ls[p][:, None], rs[q]).ravel(), n.ravel())
            if one:
                own = left[members[have[left]] > 1]
                for k, width in enumerate(kind.widths):
                    add(count[k][0], kind.score(k, np.full(len(own), float(width)) if width else size[own], size[own], size[own]), weight(have[own], have[own]))
            for p, q in linked():
                w = weight(p, q)
                p, q = back[p], back[q]
                good = (p >= 0) & (q >= 0)
                p, q, w = p[good], q[good], w[good]
                for lo_ in range(0, len(p), 4096):
                    s = slice(lo_, lo_ + 4096)
                    both = v[p[s]].astype(np.float64) * v[q[s]]
                    for k, width in enumerate(kind.widths):
                        add(count[k][1], kind.score(k, both[:, : width or None].sum(axis=1), size[p[s]], size[q[s]]), w[s])
            for k, (n, t) in enumerate(count):
                out += [(base + k, s, n.get(s, 0), t.get(s, 0), None) for s in {*n, *t}]
            base += len(kind.widths)
        return pa.table([pa.array(c, t) for c, t in zip(zip(*out), (pa.int32(), pa.int64(), pa.int64(), pa.int64(), pa.int64()))], names=["method", "score", "n", "t", "cut"])

    return dealt.groupBy("i", "j").cogroup(true.groupBy("i", "j")).applyInArrow(run, "method int, score bigint, n bigint, t bigint, cut bigint")


def best_of(rows: DataFrame, pairs: DataFrame, kinds: dict, methods: list[str], label: str, tile: int | None = None, whole: int | None = None) -> DataFrame:
    """(label, threshold, found, both, precision, recall, f1) of each method at its best threshold over all pairs.

    A threshold that a cut leaves out finds no fewer pairs than the last one counted, so its f1 has a bound; where the
    bound does not stay below the best, that fingerprint is counted again without cuts.
    """
    spark = rows.sparkSession
    ascending = not isinstance(next(iter(kinds.values())), _Cosine)
    counts = score_counts(rows, pairs, kinds, tile, whole).groupBy("method", "score").agg(F.sum("n").alias("n"), F.sum("t").alias("t"), (F.min("cut") if ascending else F.max("cut")).alias("cut")).collect()
    truth = max(next((r["t"] for r in counts if r["method"] == -1), 0), 1)
    out, m = None, 0
    for column, kind in kinds.items():
        own, sure = [], True
        for name in methods[m : m + len(kind.widths)]:
            cut = next((r["cut"] for r in counts if r["method"] == m and r["score"] is None), None)
            inside = lambda s: cut is None or (s <= cut if ascending else s >= cut)  # noqa: B023, E731
            seen = [r for r in counts if r["method"] == m and r["score"] is not None]
            per = [(r["score"] if ascending else r["score"] / GRID, r["n"], r["t"]) for r in seen if inside(r["score"]) and r["n"]]
            best = dedup.best_threshold(dedup.sweep_counts(spark.createDataFrame(per, f"score {'int' if ascending else 'double'}, n bigint, t bigint"), truth, ascending), ascending)
            own.append(best.select(F.lit(name).alias(label), "*"))
            m += 1
            if cut is not None:
                found, both = sum(n for _, n, _ in per), sum(t for _, _, t in per)
                top = best.first()
                bound = 0.0
                for r in sorted((r for r in seen if not inside(r["score"])), key=lambda r: r["score"], reverse=not ascending):
                    found, both = found + r["t"], both + r["t"]
                    bound = max(bound, 2 * both / (found + truth))
                sure &= top is not None and bound <= top["f1"]
        if not sure:
            own = [best_of(rows.select("class", column), pairs, {column: kind}, methods[m - len(kind.widths) : m], label, tile, whole=1 << 62)]
        for one in own:
            out = one if out is None else out.unionByName(one)
    return out
