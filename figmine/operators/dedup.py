"""Near-duplicate grouping by bit hash, by vector, by both, and by cascade."""

from __future__ import annotations

import hashlib
from itertools import combinations

import numpy as np
import pyarrow as pa
import pyarrow.compute as pc
from pyspark.sql import DataFrame, Window
from pyspark.sql import functions as F

from ..functions.expressions import band_keys, hamming, pack_words
from .fingerprints import kept, numbers, packed
from .graph import components

# ---- bit hashes


def collapse_equal(hashed: DataFrame) -> DataFrame:
    """(hash, id, members): one row per distinct hash, so a giant class of equal elements costs its size and no more."""
    return hashed.where("hash IS NOT NULL").groupBy("hash").agg(F.min("id").alias("id"), F.count("*").alias("members"))


def band_records(hashed: DataFrame, bands: int = 6, bits: int = 24) -> DataFrame:
    return hashed.where("hash IS NOT NULL").select("id", "hash", pack_words(F.col("hash")).alias("words"), F.explode(band_keys(F.col("hash"), bands, bits)).alias("b")).select("id", "hash", "words", "b.band", "b.value")


def bucket_sizes(hashed: DataFrame, bands: int = 6, bits: int = 24) -> DataFrame:
    return band_records(hashed, bands, bits).groupBy("band", "value").agg(F.count("*").alias("members"))


def banded_edges(hashed: DataFrame, tau: int = 16, bands: int = 6, bits: int = 24, max_bucket: int | None = None) -> DataFrame:
    """(src, dst, distance) of pairs that share a band and differ in at most ``tau`` bits; each pair once.

    A pair is taken from the first band it shares, which needs no distinct over pairs. With ``max_bucket`` larger
    buckets are left out, as the published run does; without it nothing is.
    """
    records = band_records(hashed, bands, bits)
    if max_bucket is not None:
        fits = records.groupBy("band", "value").agg(F.count("*").alias("members")).where(F.col("members") <= max_bucket).select("band", "value")
        records = records.join(fits, ["band", "value"])
    a, b = records.alias("a"), records.alias("b")
    width = bits // 4
    shared = F.lit(0)
    for k in reversed(range(bands)):
        shared = F.when(F.substring("a.hash", 1 + k * width, width) == F.substring("b.hash", 1 + k * width, width), k).otherwise(shared)
    distance = hamming(F.col("a.words"), F.col("b.words"))
    met = (F.col("a.band") == F.col("b.band")) & (F.col("a.value") == F.col("b.value")) & (F.col("a.id") < F.col("b.id")) & (distance <= tau)
    pairs = a.join(b, met if max_bucket is not None else met & (F.col("a.band") == shared)).select(F.col("a.id").alias("src"), F.col("b.id").alias("dst"), distance.alias("distance"))
    return pairs.distinct() if max_bucket is not None else pairs


def probed_edges(hashed: DataFrame, tau: int = 16, bands: int = 6, bits: int = 24, probes: int = 1) -> DataFrame:
    """(src, dst, distance) of pairs within ``tau`` bits that have a band where at most ``probes`` bits differ; each pair once.

    One side of the join asks for its band values with every choice of so many bits flipped: ``bits`` + 1 rows a band for
    one probe. A pair is taken from its first such band, as in ``banded_edges``.
    """
    width = bits // 4
    masks = F.array(*[F.lit(sum(1 << k for k in c)).cast("bigint") for r in range(probes + 1) for c in combinations(range(bits), r)])
    values = F.array(*[F.conv(F.substring("hash", 1 + k * width, width), 16, 10).cast("bigint") for k in range(bands)])
    rows = hashed.where("hash IS NOT NULL").select("id", pack_words(F.col("hash")).alias("words"), values.alias("all"))
    held = rows.select("id", "words", "all", F.posexplode("all").alias("band", "value"))
    asked = held.withColumn("value", F.explode(F.transform(masks, lambda m: F.col("value").bitwiseXOR(m))))
    a, b = asked.alias("a"), held.alias("b")
    first = F.lit(0)
    for k in reversed(range(bands)):
        first = F.when(F.bit_count(F.col("a.all")[k].bitwiseXOR(F.col("b.all")[k])) <= probes, k).otherwise(first)
    distance = hamming(F.col("a.words"), F.col("b.words"))
    met = (F.col("a.band") == F.col("b.band")) & (F.col("a.value") == F.col("b.value")) & (F.col("a.id") < F.col("b.id")) & (F.col("a.band") == first) & (distance <= tau)
    return a.join(b, met).select(F.col("a.id").alias("src"), F.col("b.id").alias("dst"), distance.alias("distance"))


#: 144 bits are nine bands of 16; pairs that differ in fewer than 18 bits have a band where at most one bit differs.
NEAR_BANDS, NEAR_LIMIT = 9, 17
#: Candidates that a worker expands at once.
NEAR_STEP = 1 << 20


def _near_in(key: int, words: np.ndarray, tau: int) -> tuple[np.ndarray, np.ndarray, np.ndarray]:
    """Row numbers of the pairs of one group, and their differing bits as words. ``key`` says which band and which half of
    it the rows share; the other half differs in one bit at most (where it is the lower one) or in exactly one."""
    band, half = key >> 9, key >> 8 & 1
    shift = lambda k: np.uint64(48 - 16 * (k % 4) if k < 8 else 0)
    other = (words[band // 4] >> shift(band) & np.uint64(0xFFFF)).astype(np.int64)
    other = other & 0xFF if half == 0 else other >> 8
    order = np.argsort(other, kind="stable")
    other, words = other[order], words[:, order]
    starts = np.searchsorted(other, np.arange(257))
    wanted = (other[:, None] ^ np.array([*([0] if half == 0 else []), *(1 << np.arange(8))])).ravel()
    row = np.repeat(np.arange(len(other)), len(wanted) // max(len(other), 1))
    # each pair from one side: the smaller other half, or the earlier row where both are equal
    lo = np.where(wanted == other[row], row + 1, starts[wanted])
    count = np.where(wanted >= other[row], starts[wanted + 1] - lo, 0)
    row, lo, count = row[count > 0], lo[count > 0], count[count > 0]
    ends = np.cumsum(count)
    found = []
    at = 0
    while at < len(count):
        to = max(at + 1, int(np.searchsorted(ends, (ends[at - 1] if at else 0) + NEAR_STEP, "right")))
        n = count[at:to]
        x = np.repeat(row[at:to], n)
        y = np.arange(n.sum()) + np.repeat(lo[at:to] - (np.cumsum(n) - n), n)
        at = to
        bits = np.zeros(len(x), np.uint8)
        for w in words:
            bits = bits + np.bitwise_count(w[x] ^ w[y])
            near = bits <= tau
            x, y, bits = x[near], y[near], bits[near]
        diff = words[:, x] ^ words[:, y]
        first = np.ones(len(x), bool)
        for k in range(band):
            first &= np.bitwise_count(diff[k // 4] >> shift(k) & np.uint64(0xFFFF)) > 1
        found.append((order[x[first]], order[y[first]], diff[:, first]))
    if not found:
        return np.zeros(0, np.int64), np.zeros(0, np.int64), words[:, :0]
    return np.concatenate([f[0] for f in found]), np.concatenate([f[1] for f in found]), np.concatenate([f[2] for f in found], axis=1)


def near_classes(classes: DataFrame, tau: int = 16) -> DataFrame:
    """(a, b, m, n, distance, diff): all pairs of distinct hashes within ``tau`` (at most ``NEAR_LIMIT``) bits, each once,
    with their classes' ids and members and the differing bits as 36 hex digits. Exact, without comparing all pairs: such
    a pair agrees in one half of some band but for one bit of the other half, so rows meet by half bands of 8 bits.
    """
    if tau > NEAR_LIMIT:
        raise ValueError(f"at most {NEAR_LIMIT} bits")
    w = pack_words(F.col("hash"))
    part = lambda k, h: F.conv(F.substring("hash", 1 + 4 * k + 2 * h, 2), 16, 10).cast("int") + ((2 * k + h) << 8)
    keys = F.explode(F.array(*[part(k, h) for k in range(NEAR_BANDS) for h in (0, 1)]))
    kind = classes.schema["id"].dataType.simpleString()

    def run(key, table):
        words = np.stack([table.column(c).to_numpy().astype(np.int64).view(np.uint64) for c in ("w0", "w1", "w2")])
        x, y, diff = _near_in(key[0].as_py(), words, tau)
        ids, members = table.column("id").combine_chunks(), table.column("members").combine_chunks()
        return pa.table([ids.take(pa.array(x)), ids.take(pa.array(y)), members.take(pa.array(x)), members.take(pa.array(y)), *(pa.array(d.view(np.int64)) for d in diff)], names=["a", "b", "m", "n", "d0", "d1", "d2"])

    met = classes.select("id", "members", w.alias("w"), keys.alias("key")).select("id", "members", "w.*", "key")
    found = met.groupBy("key").applyInArrow(run, f"a {kind}, b {kind}, m bigint, n bigint, d0 bigint, d1 bigint, d2 bigint")
    distance = F.bit_count("d0") + F.bit_count("d1") + F.bit_count("d2")
    diff = F.concat(F.lpad(F.hex("d0"), 16, "0"), F.lpad(F.hex("d1"), 16, "0"), F.lpad(F.hex("d2"), 4, "0"))
    return found.select("a", "b", "m", "n", distance.alias("distance"), diff.alias("diff"))


def exhaustive_edges(hashed: DataFrame, tau: int = 16) -> DataFrame:
    """(src, dst, distance) of all pairs within ``tau`` bits, for measuring what banding finds."""
    if tau > NEAR_LIMIT:
        h = hashed.where("hash IS NOT NULL").select("id", pack_words(F.col("hash")).alias("words"))
        a, b = h.alias("a"), h.alias("b")
        distance = hamming(F.col("a.words"), F.col("b.words"))
        return a.join(b, (F.col("a.id") < F.col("b.id")) & (distance <= tau)).select(F.col("a.id").alias("src"), F.col("b.id").alias("dst"), distance.alias("distance"))
    classes = collapse_equal(hashed)
    rows = hashed.join(classes.select("hash", F.col("id").alias("class")), "hash").select("id", "class")
    pairs = near_classes(classes, tau).select("a", "b", "distance").unionByName(classes.where("members > 1").select(F.col("id").alias("a"), F.col("id").alias("b"), F.lit(0).alias("distance")))
    x, y = rows.select(F.col("id").alias("x"), F.col("class").alias("a")), rows.select(F.col("id").alias("y"), F.col("class").alias("b"))
    met = pairs.join(x, "a").join(y, "b").where(((F.col("a") != F.col("b")) & (F.col("x") != F.col("y"))) | (F.col("x") < F.col("y")))
    return met.select(F.least("x", "y").alias("src"), F.greatest("x", "y").alias("dst"), "distance")


def found_counts(hashed: DataFrame, ways: list[tuple[int, int, int]], tau: int = 16) -> DataFrame:
    """One row: ``exhaustive``, all pairs within ``tau`` bits, and ``found0``, ``found1``, ... for each way (bands, bits,
    probes) those with a band where at most so many bits differ: the pairs of ``banded_edges`` and ``probed_edges``."""
    classes = collapse_equal(hashed)
    weight = F.col("m") * F.col("n")
    met = []
    for bands, bits, probes in ways:
        width = bits // 4
        hit = F.lit(False)
        for k in range(bands):
            hit = hit | (F.bit_count(F.conv(F.substring("diff", 1 + k * width, width), 16, 10).cast("bigint")) <= probes)
        met.append(hit)
    pairs = near_classes(classes, tau).agg(F.coalesce(F.sum(weight), F.lit(0)).alias("exhaustive"), *[F.coalesce(F.sum(F.when(h, weight)), F.lit(0)).alias(f"found{k}") for k, h in enumerate(met)])
    equal = classes.agg(F.coalesce(F.sum(F.col("members") * (F.col("members") - 1) / 2), F.lit(0)).cast("bigint").alias("equal"))
    return pairs.join(equal, how="cross").select(*[(F.col(c) + F.col("equal")).alias(c) for c in pairs.columns])


def hash_groups(hashed: DataFrame, tau: int = 16, bands: int = 6, bits: int = 24) -> DataFrame:
    """(id, group_id) over all ids; equal hashes are one class before banding."""
    classes = collapse_equal(hashed)
    found = components(banded_edges(classes, tau, bands, bits))
    named = classes.join(found, classes["id"] == found["node"], "left").select("hash", F.coalesce("component", "id").alias("group_id"))
    return hashed.select("id", "hash").join(named, "hash", "left").select("id", F.coalesce("group_id", "id").alias("group_id"))


def wide_edges(hashed: DataFrame) -> DataFrame:
    """(src, dst, distance) of all pairs of hashes of any length: the baseline that sweeps of hash sizes are scored on."""
    digits = F.length("hash")
    words = F.transform(F.sequence(F.lit(1), digits, F.lit(8)), lambda i: F.conv(F.substring(F.col("hash"), i, F.lit(8)), 16, 10).cast("long"))
    h = hashed.where("hash IS NOT NULL").select("id", words.alias("w"))
    a, b = h.alias("a"), h.alias("b")
    distance = F.aggregate(F.zip_with("a.w", "b.w", lambda x, y: F.bit_count(x.bitwiseXOR(y))), F.lit(0), lambda s, x: s + x)
    return a.join(b, F.col("a.id") < F.col("b.id")).select(F.col("a.id").alias("src"), F.col("b.id").alias("dst"), distance.alias("distance"))


# ---- vectors


def cosine_edges(vectors: DataFrame, least: float = 0.86, tile: int = 2048, forest: bool = False) -> DataFrame:
    """(src, dst, similarity) of all pairs at or above ``least``: exact, tile by tile of bounded size.

    ``forest`` keeps of each pair of tiles only the edges of a spanning forest: the same components from at most one edge
    a vector and tile, where a class of many equal vectors would give the square of its size.
    """
    rows = vectors.where("vec IS NOT NULL").select("id", "vec")
    n = rows.count()
    tiles = max(1, -(-n // tile))
    rows = rows.withColumn("t", F.pmod(F.xxhash64("id"), F.lit(tiles)))
    dealt = rows.withColumn("u", F.explode(F.sequence(F.lit(0), F.lit(tiles - 1)).cast("array<bigint>"))).select("id", "vec", "t", F.least("t", "u").alias("i"), F.greatest("t", "u").alias("j"))
    kind = vectors.schema["id"].dataType.simpleString()

    def run(key, table):
        i, j = key[0].as_py(), key[1].as_py()
        t = table.column("t").to_numpy()
        ids = table.column("id").combine_chunks()
        order = np.empty(len(ids), np.int64)
        order[pc.sort_indices(ids).to_numpy()] = np.arange(len(ids))
        v = np.array(table.column("vec").to_pylist())
        p, q = np.flatnonzero(t == i), np.flatnonzero(t == j)
        sims = v[p] @ v[q].T if len(p) and len(q) else np.zeros((0, 0))
        a, b = np.nonzero(sims >= least)
        score = sims[a, b]
        a, b = p[a], q[b]
        once = order[a] < order[b] if i == j else a != b
        a, b, score = a[once], b[once], score[once]
        swap = order[a] > order[b]
        a, b = np.where(swap, b, a), np.where(swap, a, b)
        if forest and len(a):
            label, keep = np.arange(len(ids)), np.zeros(len(a), bool)
            by = np.argsort(a, kind="stable")
            for lo, hi in zip(*(lambda x: (x, [*x[1:], len(a)]))(np.flatnonzero(np.diff(a[by], prepend=-1)))):
                row = by[lo:hi]
                own = label[a[row[0]]]
                labels, first = np.unique(label[b[row]], return_index=True)
                new = labels != own
                if new.any():
                    keep[row[first[new]]] = True
                    label[np.isin(label, labels[new])] = own
            a, b, score = a[keep], b[keep], score[keep]
        return pa.table([ids.take(pa.array(a)), ids.take(pa.array(b)), pa.array(score, pa.float64())], names=["src", "dst", "similarity"])

    return dealt.groupBy("i", "j").applyInArrow(run, f"src {kind}, dst {kind}, similarity double")


#: Share of a vector's components that stands for it in the search, and what rounding may add to its bound.
HEAD, SLACK = 0.3, 2e-3


def similar(pairs: DataFrame, vectors: DataFrame, least: float) -> DataFrame:
    """The (src, dst) of ``pairs`` whose vectors (id, packed) have a cosine of ``least`` or more."""
    kind = vectors.schema["id"].dataType.simpleString()
    v = vectors.where("packed IS NOT NULL")
    met = pairs.select("src", "dst").join(v.select(F.col("id").alias("src"), F.col("packed").alias("x")), "src").join(v.select(F.col("id").alias("dst"), F.col("packed").alias("y")), "dst").select("src", "dst", "x", "y")

    def run(batches):
        for batch in batches:
            keep = []
            for x, y in zip(batch.column(2).to_pylist(), batch.column(3).to_pylist()):
                p, q = numbers(x), numbers(y)
                size = np.sqrt(p @ p) * np.sqrt(q @ q)
                keep.append(bool(size > 0 and p @ q >= least * size))
            yield batch.select([0, 1]).filter(pa.array(keep, pa.bool_()))

    return met.mapInArrow(run, f"src {kind}, dst {kind}")


def near_vectors(vectors: DataFrame, least: float = 0.86, tile: int = 65536) -> DataFrame:
    """(src, dst) whose components are those of all pairs with a cosine of ``least`` or more; exact. ``vectors`` has (id,
    packed), vectors of one length.

    Equal vectors are one class, whose members meet its smallest id. Of the others, tiles of bounded size meet with the
    head of each vector only: the product of two heads and of the lengths of the two rests bounds the cosine from above,
    and what the bound leaves is worked out in full.
    """
    kind = vectors.schema["id"].dataType.simpleString()

    def heads(batches):
        for batch in batches:
            ids, heads, marks = [], [], []
            for k, one in enumerate(batch.column(1).to_pylist()):
                v = numbers(one)
                size = float(np.sqrt(v @ v))
                if size > 0:
                    v = v / size
                    n = max(1, int(len(v) * HEAD))
                    ids.append(k)
                    heads.append(np.append(v[:n], np.sqrt(v[n:] @ v[n:])).astype(np.float16).tobytes())
                    marks.append(hashlib.blake2b(one, digest_size=16).digest())
            yield pa.RecordBatch.from_arrays([batch.column(0).take(pa.array(ids, pa.int64())), pa.array(heads, pa.binary()), pa.array(marks, pa.binary())], names=["id", "head", "mark"])

    rows = kept(vectors.where("packed IS NOT NULL").select("id", "packed").mapInArrow(heads, f"id {kind}, head binary, mark binary"))
    classes = rows.groupBy("mark").agg(F.min("id").alias("src"))
    equal = rows.join(classes, "mark").where("src < id").select("src", F.col("id").alias("dst"))
    alone = kept(rows.join(classes.select(F.col("src").alias("id")), "id", "left_semi").select("id", "head"))
    tiles = max(1, -(-alone.count() // tile))
    own = F.pmod(F.xxhash64("id"), F.lit(tiles))
    dealt = alone.withColumn("t", own).withColumn("u", F.explode(F.sequence(F.lit(0), F.lit(tiles - 1)).cast("array<bigint>"))).select("id", "head", "t", F.least("t", "u").alias("i"), F.greatest("t", "u").alias("j"))

    def run(key, table):
        i, j = key[0].as_py(), key[1].as_py()
        t = table.column("t").to_numpy()
        ids = table.column("id").combine_chunks()
        v = np.frombuffer(b"".join(table.column("head").to_pylist()), np.float16).reshape(len(ids), -1)
        p, q = np.flatnonzero(t == i), np.flatnonzero(t == j)
        right = v[q].astype(np.float32).T
        left, other = [np.zeros(0, np.int64)], [np.zeros(0, np.int64)]
        for at in range(0, len(p), 256):
            bound = v[p[at : at + 256]].astype(np.float32) @ right
            hit = np.flatnonzero(bound.ravel() >= least - SLACK) if bound.size and bound.max() >= least - SLACK else np.zeros(0, np.int64)
            a, b = hit // max(len(q), 1) + at, hit % max(len(q), 1)
            once = a < b if i == j else slice(None)
            left.append(p[a[once]])
            other.append(q[b[once]])
        return pa.table([ids.take(pa.array(np.concatenate(left))), ids.take(pa.array(np.concatenate(other)))], names=["src", "dst"])

    found = dealt.groupBy("i", "j").applyInArrow(run, f"src {kind}, dst {kind}")
    return equal.unionByName(similar(found, vectors, least))


def vector_groups(vectors: DataFrame, least: float = 0.86, edges: DataFrame | None = None) -> DataFrame:
    """(id, group_id); ``vectors`` has (id, vec) or (id, packed)."""
    if edges is None:
        vectors = vectors if "packed" in vectors.columns else kept(packed(vectors.select("id", "vec")))
        edges = near_vectors(vectors, least)
    return assign(vectors, components(edges))


# ---- grouping


def assign(ids: DataFrame, found: DataFrame) -> DataFrame:
    """(id, group_id); an element without an edge is a group of its own."""
    return ids.select("id").join(found, F.col("id") == F.col("node"), "left").select("id", F.coalesce("component", "id").alias("group_id"))


def intersect_groups(by_hash: DataFrame, by_vector: DataFrame) -> DataFrame:
    """(id, hash_group, vector_group, group_id): elements are one group only where both groupings agree."""
    both = by_hash.select("id", F.col("group_id").alias("hash_group")).join(by_vector.select("id", F.col("group_id").alias("vector_group")), "id")
    least = both.groupBy("hash_group", "vector_group").agg(F.min("id").alias("group_id"))
    return both.join(least, ["hash_group", "vector_group"]).select("id", "hash_group", "vector_group", "group_id")


def cascade_groups(hashed: DataFrame, vectors: DataFrame, least: float = 0.86, tau: int = 16) -> DataFrame:
    """(id, group_id): the cosine is worked out for banded pairs only. Equal hashes meet their smallest member."""
    classes = collapse_equal(hashed)
    star = hashed.join(classes.select("hash", F.col("id").alias("src")), "hash").where("src < id").select("src", F.col("id").alias("dst"))
    pairs = banded_edges(classes, tau).select("src", "dst").unionByName(star)
    vectors = vectors if "packed" in vectors.columns else kept(packed(vectors.select("id", "vec")))
    return assign(hashed, components(similar(pairs, vectors, least)))


def representatives(elements: DataFrame, group: str = "group_id", confidence: str = "detection_confidence") -> DataFrame:
    """(group, id): the most confident member, ties to the smallest id."""
    return elements.groupBy(group).agg(F.max_by("id", F.struct(F.col(confidence), -F.col("id"))).alias("id"))


def group_stats(groups: DataFrame) -> DataFrame:
    """One row: elements, groups, share removed, share of groups with one member, largest group."""
    sizes = groups.groupBy("group_id").agg(F.count("*").alias("members"))
    return sizes.agg(
        F.sum("members").alias("elements"),
        F.count("*").alias("groups"),
        F.round(1 - F.count("*") / F.sum("members"), 6).alias("reduction"),
        F.round(F.avg((F.col("members") == 1).cast("int")), 6).alias("singleton_share"),
        F.max("members").alias("largest"),
    )


def group_sizes(groups: DataFrame) -> DataFrame:
    return groups.groupBy("group_id").agg(F.count("*").alias("members")).groupBy("members").agg(F.count("*").alias("groups"))


# ---- accuracy


def pair_metrics(found: DataFrame, truth: DataFrame) -> DataFrame:
    """One row: pairs found, true pairs, both, precision, recall, f1. Pairs are (src, dst) with src < dst."""
    f, t = found.select("src", "dst").distinct(), truth.select("src", "dst").distinct()
    j = f.withColumn("f", F.lit(1)).join(t.withColumn("t", F.lit(1)), ["src", "dst"], "full_outer")
    counts = j.agg(F.count("f").alias("found"), F.count("t").alias("truth"), F.count(F.col("f") + F.col("t")).alias("both"))
    p, r = F.col("both") / F.when(F.col("found") > 0, F.col("found")), F.col("both") / F.when(F.col("truth") > 0, F.col("truth"))
    return counts.select("found", "truth", "both", F.round(p, 6).alias("precision"), F.round(r, 6).alias("recall"), F.round(2 * p * r / F.when(p + r > 0, p + r), 6).alias("f1"))


def sweep(scored: DataFrame, truth_pairs: int, ascending: bool = False) -> DataFrame:
    """(threshold, found, both, precision, recall, f1) at every distinct score; ``scored`` has score and is_true."""
    return sweep_counts(scored.groupBy("score").agg(F.count("*").alias("n"), F.sum(F.col("is_true").cast("int")).alias("t")), truth_pairs, ascending)


def sweep_counts(per: DataFrame, truth_pairs: int, ascending: bool = False) -> DataFrame:
    """``sweep`` of scores that are counted already; ``per`` has score, n pairs and t true ones among them."""
    order = Window.orderBy(F.asc("score") if ascending else F.desc("score")).rowsBetween(Window.unboundedPreceding, 0)
    run = per.select(F.col("score").alias("threshold"), F.sum("n").over(order).alias("found"), F.sum("t").over(order).alias("both"))
    p, r = F.col("both") / F.col("found"), F.col("both") / F.lit(truth_pairs)
    return run.select("threshold", "found", "both", F.round(p, 6).alias("precision"), F.round(r, 6).alias("recall"), F.round(2 * p * r / F.when(p + r > 0, p + r), 6).alias("f1"))


def best_threshold(swept: DataFrame, ascending: bool = False) -> DataFrame:
    """The threshold of the best f1; ties go to the stricter one."""
    return swept.where("f1 IS NOT NULL").orderBy(F.desc("f1"), F.asc("threshold") if ascending else F.desc("threshold")).limit(1)
