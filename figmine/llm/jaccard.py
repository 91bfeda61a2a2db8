"""N-gram Jaccard join: documents whose sets of word n-grams overlap by a share of their union, and their groups.

1. One scan turns each text into its set of 64-bit n-gram hashes and a 128-bit fingerprint of that set. Texts with equal
   sets are one class from then on, so copies never meet one another in the join.
2. The same scan asks how common each n-gram is. It writes its n-grams chunk by chunk (``CHUNK`` n-grams of one task),
   sorted and cut into pieces of the hash range; a piece counts the n-grams of all chunks and answers each chunk with
   those that occur more than once. Pieces follow the input, so the frequencies are as exact at any size. N-grams common
   within a chunk are asked for once per chunk, so none makes a piece long.
3. (count, hash) orders the n-grams of a class rare-first, and the prefix filter shows the first n - ceil(t n) + 1 of
   them to others. Those that occur once come first in that order; they have no partner and are not sent.
4. Classes meet where they show the same n-gram. There a pair must pass, in this order, the length filter, the first
   shared n-gram rule (a pair is looked at where its first common prefix n-gram is, and nowhere else), the positional
   filter, and the suffix filter, which bounds the overlap by how the n-grams of both spread over ``BINS`` bins.
   A list longer than ``TILE`` is dealt out as pairs of tiles, so no task holds an unbounded list and none is cut off.
5. What is left is verified once per pair against the whole sets, which are made again from the texts it needs.

Nulls and edge cases: a null or blank text has an empty set and no link; fewer words than n make one n-gram of all of
them; repeated rows are copies; a null id takes part but cannot name a group, and a group of null ids has a null
component; extra columns are ignored; an empty table gives an empty result.
"""

from __future__ import annotations

import hashlib

import numpy as np
import pyarrow as pa
from pyspark import TaskContext
from pyspark.sql import DataFrame, Window
from pyspark.sql import functions as F

from ..operators.graph import components
from . import textvec as V
from .common import Scratch, bounded_batches, free_names

#: N-grams and documents of a chunk at most (but for the last text of it).
CHUNK = 2_000_000
CHUNK_DOCS = 60_000
#: Bits by which a piece tells n-grams apart, and bytes of text a piece stands for: 64 values for each n-gram.
VALUE_BITS = 28
PIECE_BYTES = 12 << 20
#: An n-gram in so many documents of a chunk is asked for once.
HEAVY = 8
#: Bits of the bitmap that keeps texts which nobody needs from being shuffled, and bits in a row of it.
MARKS = 1 << 25
MARK_ROW = 1 << 16
BINS = 128
#: Parts that the copies of one class are dealt to.
SALTS = 4096
TILE = 2048
FP_BYTES = 16
#: First bytes of a fingerprint that tell the classes of one family apart.
NAME_BYTES = 8
#: Lists up to this length are compared pair by pair, longer ones as arrays.
SHORT = 8
#: Earlier n-grams of a class that are looked at first, for all its pairs at once.
HEAD = 32
#: Edges of a graph that one task groups at most; a larger graph is grouped in rounds by all.
EDGES = 1 << 18


def _set_of(hashes: np.ndarray, n: int) -> np.ndarray:
    """Sorted distinct n-grams of one text."""
    if not len(hashes):
        return hashes
    width = min(n, len(hashes))
    count = len(hashes) - width + 1
    gram = np.full(count, width, np.uint64)
    for k in range(width):
        gram = V.mix(gram * np.uint64(0x100000001B3) + hashes[k : k + count])
    return np.unique(gram)


def _spread_of(grams: np.ndarray) -> bytes:
    bins = np.bincount((grams >> np.uint64(40)).astype(np.int64) % BINS, minlength=BINS)
    return bins.astype(np.uint8 if bins.max() < 256 else np.uint32).tobytes()


def _sets(column: pa.Array, n: int):
    """Yields (row, sorted set of n-grams) of each text."""
    for first, step in V.steps(column):
        start, end, bounds = step.words(V.SPACES)
        hashes = step.span_hash(start, end)
        for k in range(len(bounds) - 1):
            yield first + k, _set_of(hashes[bounds[k] : bounds[k + 1]], n)


def _name(grams: np.ndarray) -> bytes:
    """The fingerprint of a set."""
    return hashlib.blake2b(grams.tobytes(), digest_size=FP_BYTES).digest()


def _planes(x: np.ndarray, width: int) -> bytes:
    """The lowest ``width`` bytes of each number, all lowest bytes first: high bytes are mostly 0 and compress away."""
    return np.ascontiguousarray(x.astype("<u4").view(np.uint8).reshape(-1, 4)[:, :width].T).tobytes()


def _unplaned(raw: bytes, width: int) -> np.ndarray:
    out = np.zeros((len(raw) // width, 4), np.uint8)
    out[:, :width] = np.frombuffer(raw, np.uint8).reshape(width, -1).T
    return out.reshape(-1).view("<u4")


#: Rows of documents, of questions to a piece, and of what a chunk keeps to understand the answers.
DOC, ASK, KEEP = 0, 1, 2
SCAN = "kind tinyint, doc_id {}, fp binary, n_shingles bigint, spread binary, piece int, chunk bigint, a binary, b binary, c binary"


def scan(docs: DataFrame, pieces: int, doc_id: str = "doc_id", text: str = "text", n: int = 3, per_chunk: int = CHUNK) -> DataFrame:
    """One pass over the texts.

    ``DOC``: doc_id, fp, n_shingles, spread (how many n-grams fall into each of ``BINS`` bins). ``ASK``: for a piece and
    a chunk, the n-grams as differences (a), the document in the chunk that has each (b) and how many have it (c).
    ``KEEP``: fingerprints (a) and set sizes (b) of a chunk's documents, and its heavy n-grams with their documents (c).
    """
    kind = docs.schema[doc_id].dataType.simpleString()

    def run(batches):
        seen: set[bytes] = set()
        task, flushed = TaskContext.get().partitionId(), 0
        held, fps, sizes, total = [], [], [], 0

        def rows(kinds, ids=None, **values):
            count = len(kinds)
            columns = {"kind": pa.array(kinds, pa.int8()), "doc_id": pa.nulls(count, ids_type) if ids is None else ids}
            for name, type_ in (("fp", pa.binary()), ("n_shingles", pa.int64()), ("spread", pa.binary()), ("piece", pa.int32()), ("chunk", pa.int64()), ("a", pa.binary()), ("b", pa.binary()), ("c", pa.binary())):
                columns[name] = pa.array(values[name], type_) if name in values else pa.nulls(count, type_)
            return pa.RecordBatch.from_arrays(list(columns.values()), names=list(columns))

        def flush():
            chunk = (task << 24) + flushed
            which = np.repeat(np.arange(len(held), dtype=np.uint16), [len(x) for x in held])
            value = np.concatenate(held)
            held.clear()
            # piece, value in the piece and document in one number, in place
            packed = value >> np.uint64(32)
            packed *= np.uint64(pieces)
            packed >>= np.uint64(32)
            packed <<= np.uint64(VALUE_BITS)
            value &= np.uint64((1 << VALUE_BITS) - 1)
            packed |= value
            packed <<= np.uint64(16)
            packed |= which
            del value, which
            packed.sort()
            key = packed >> np.uint64(16)
            starts = np.flatnonzero(np.concatenate([[True], key[1:] != key[:-1]]))
            often = np.diff(np.append(starts, len(key)))
            heavy = often >= HEAVY
            inside = np.repeat(heavy, often)
            heavy_key, heavy_n, heavy_docs = key[starts[heavy]], often[heavy], packed[inside] & np.uint64(0xFFFF)
            first = ~inside
            first[starts[heavy]] = True
            many = np.ones(len(key), np.uint16)
            many[starts[heavy]] = np.minimum(heavy_n, 0xFFFF)
            del key, starts, often, heavy, inside
            packed, many = packed[first], many[first]
            at = (packed >> np.uint64(VALUE_BITS + 16)).astype(np.int32)
            cuts = np.flatnonzero(np.diff(at)) + 1
            bounds = [0, *cuts.tolist(), len(at)]
            spans = list(zip(bounds, bounds[1:]))
            yield rows(
                [ASK] * len(spans),
                piece=[int(at[lo]) for lo, _ in spans],
                chunk=[chunk] * len(spans),
                a=[_planes(np.diff((packed[lo:hi] >> np.uint64(16)) & np.uint64((1 << VALUE_BITS) - 1), prepend=np.uint64(0)), 4) for lo, hi in spans],
                b=[_planes(packed[lo:hi] & np.uint64(0xFFFF), 2) for lo, hi in spans],
                c=[_planes(many[lo:hi], 2) for lo, hi in spans],
            )
            del packed, many, at
            head = np.array([len(heavy_key)], np.int64)
            yield rows([KEEP], chunk=[chunk], a=[b"".join(fps)], b=[np.array(sizes, np.int64).tobytes()], c=[head.tobytes() + heavy_key.tobytes() + heavy_n.tobytes() + heavy_docs.astype("<u2").tobytes()])

        for batch in batches:
            ids, ids_type = batch.column(0), batch.column(0).type
            names, lengths, spreads = [], [], []
            for _, grams in _sets(batch.column(1), n):
                name = _name(grams)
                names.append(name)
                lengths.append(len(grams))
                spreads.append(_spread_of(grams))
                if len(grams) and name not in seen:
                    seen.add(name)
                    held.append(grams)
                    fps.append(name)
                    sizes.append(len(grams))
                    total += len(grams)
                    if total >= per_chunk or len(held) >= CHUNK_DOCS:
                        yield from flush()
                        held, fps, sizes, total, flushed = [], [], [], 0, flushed + 1
            yield rows([DOC] * len(names), ids, fp=names, n_shingles=lengths, spread=spreads)
        if held:
            yield from flush()

    return docs.select(F.col(doc_id).alias("doc_id"), text).mapInArrow(run, SCAN.format(kind))


def _answer(key, table):
    """For each chunk that asked this piece, its n-grams that occur more than once, and how often on a scale of logarithms."""
    values, whose, documents, many = [], [], [], []
    chunks = table.column("chunk").to_pylist()
    for k, (a, b, c) in enumerate(zip(*(table.column(x).to_pylist() for x in "abc"))):
        values.append(np.cumsum(_unplaned(a, 4), dtype=np.uint32))
        documents.append(_unplaned(b, 2).astype(np.uint16))
        many.append(_unplaned(c, 2).astype(np.uint16))
        whose.append(np.full(len(documents[-1]), k, np.int32))
    value, whose, document, many = (np.concatenate(x) for x in (values, whose, documents, many))
    del values, documents
    order = np.argsort(value, kind="stable")
    value, whose, document, many = value[order], whose[order], document[order], many[order]
    starts = np.flatnonzero(np.concatenate([[True], value[1:] != value[:-1]]))
    total = np.add.reduceat(many, starts, dtype=np.int64)
    level = np.minimum(np.rint(8 * np.log2(np.maximum(total, 1))), 255).astype(np.uint8)
    length = np.diff(np.append(starts, len(value)))
    shared = np.repeat(total > 1, length)
    value, whose, document, level = value[shared], whose[shared], document[shared], np.repeat(level, length)[shared]
    order = np.argsort(whose, kind="stable")
    value, whose, document, level = value[order], whose[order], document[order], level[order]
    cuts = [0, *(np.flatnonzero(np.diff(whose)) + 1).tolist(), len(whose)] if len(whose) else [0]
    spans = list(zip(cuts, cuts[1:]))
    whole = (np.int64(key[0].as_py()) << VALUE_BITS) | value.astype(np.int64)
    return pa.table(
        {
            "chunk": pa.array([chunks[whose[lo]] for lo, _ in spans], pa.int64()),
            "keys": pa.array([whole[lo:hi].tobytes() for lo, hi in spans], pa.binary()),
            "docs": pa.array([document[lo:hi].astype("<u2").tobytes() for lo, hi in spans], pa.binary()),
            "levels": pa.array([level[lo:hi].tobytes() for lo, hi in spans], pa.binary()),
        }
    )


def _prefixes_of_chunk(percent: int):
    def run(kept, answers):
        none = pa.table({"token": pa.array([], pa.int64()), "fp": pa.array([], pa.binary()), "place": pa.array([], pa.int32()), "size": pa.array([], pa.int64())})
        if not len(answers) or not len(kept):
            return none
        names = kept.column("a")[0].as_py()
        size = np.frombuffer(kept.column("b")[0].as_py(), np.int64)
        raw = kept.column("c")[0].as_py()
        heavies = int(np.frombuffer(raw[:8], np.int64)[0])
        heavy_key = np.frombuffer(raw, np.int64, heavies, 8)
        heavy_n = np.frombuffer(raw, np.int64, heavies, 8 + 8 * heavies)
        heavy_docs = np.frombuffer(raw, "<u2", -1, 8 + 16 * heavies)
        heavy_from = np.cumsum(heavy_n) - heavy_n
        token = np.concatenate([np.frombuffer(x, np.int64) for x in answers.column("keys").to_pylist()])
        doc = np.concatenate([np.frombuffer(x, "<u2") for x in answers.column("docs").to_pylist()])
        level = np.concatenate([np.frombuffer(x, np.uint8) for x in answers.column("levels").to_pylist()])
        at = V.position_of(heavy_key, token)
        known = np.flatnonzero(at >= 0)
        if len(known):
            n = heavy_n[at[known]]
            inside = np.repeat(heavy_from[at[known]] - (np.cumsum(n) - n), n) + np.arange(n.sum())
            rest = at < 0
            token = np.concatenate([token[rest], np.repeat(token[known], n)])
            level = np.concatenate([level[rest], np.repeat(level[known], n)])
            doc = np.concatenate([doc[rest], heavy_docs[inside]])
        order = np.lexsort((token, level, doc))
        token, doc = token[order], doc[order]
        shared = np.bincount(doc, minlength=len(size))
        # the place of a document's first shared n-gram is the number of those that it alone has
        place = np.arange(len(doc), dtype=np.int32) + (size - np.cumsum(shared)).astype(np.int32)[doc]
        show = place < (size - -(-percent * size // 100) + 1).astype(np.int32)[doc]
        show[1:] &= (token[1:] != token[:-1]) | (doc[1:] != doc[:-1])
        token, doc, place = token[show], doc[show], place[show]
        fps = pa.array([names[k * FP_BYTES : (k + 1) * FP_BYTES] for k in range(len(size))], pa.binary())
        return pa.table({"token": pa.array(token), "fp": fps.take(pa.array(doc)), "place": pa.array(place), "size": pa.array(size[doc])})

    return run


def prefixes(scanned: DataFrame, percent: int) -> DataFrame:
    """(token, fp, place, size): one small row per prefix n-gram that occurs more than once."""
    asked = scanned.where(F.col("kind") == ASK).select("piece", "chunk", "a", "b", "c")
    answers = asked.groupBy("piece").applyInArrow(_answer, "chunk bigint, keys binary, docs binary, levels binary")
    kept = scanned.where(F.col("kind") == KEEP).select("chunk", "a", "b", "c")
    rows = kept.groupBy("chunk").cogroup(answers.groupBy("chunk")).applyInArrow(_prefixes_of_chunk(percent), "token bigint, fp binary, place int, size bigint")
    return rows.repartition("token").dropDuplicates(["token", "fp"])


def _pieces(docs: DataFrame, text: str) -> int:
    amount = docs.agg(F.sum(F.octet_length(text).cast("bigint"))).first()[0] or 0
    return min(max(int(docs.sparkSession.conf.get("spark.sql.shuffle.partitions")), -(-amount // PIECE_BYTES)), 1 << 20)


def _marks(wanted: DataFrame) -> np.ndarray:
    """A bitmap of the fingerprints in ``wanted``: ``MARKS`` bits whatever the input."""

    def count(batches):
        for batch in batches:
            h = np.array([int.from_bytes(fp[:8], "little") % MARKS for fp in batch.column(0).to_pylist()], np.int64)
            if len(h):
                h = np.unique(h)
                cuts = np.flatnonzero(np.diff(h // MARK_ROW)) + 1
                found = np.split(h, cuts)
                yield pa.RecordBatch.from_arrays([pa.array([int(x[0] // MARK_ROW) for x in found], pa.int32()), pa.array([(x % MARK_ROW).astype("<u2").tobytes() for x in found], pa.binary())], names=["part", "at"])

    def add(key, table):
        bits = np.zeros(MARK_ROW, bool)
        for raw in table.column("at").to_pylist():
            bits[np.frombuffer(raw, "<u2")] = True
        return pa.table({"part": pa.array([key[0].as_py()], pa.int32()), "bits": pa.array([np.packbits(bits).tobytes()], pa.binary())})

    out = np.zeros(MARKS // 8, np.uint8)
    for row in wanted.mapInArrow(count, "part int, at binary").groupBy("part").applyInArrow(add, "part int, bits binary").collect():
        out[row["part"] * MARK_ROW // 8 : (row["part"] + 1) * MARK_ROW // 8] = np.frombuffer(row["bits"], np.uint8)
    return out


def _wanted_sets(docs: DataFrame, wanted: DataFrame, text: str, n: int) -> DataFrame:
    """(fp, grams) of the wanted classes, once each. Texts travel, and a bitmap keeps most others where they are."""
    marks = docs.sparkSession.sparkContext.broadcast(_marks(wanted.select("fp")))

    def find(batches):
        bits = marks.value
        seen: set[bytes] = set()
        for batch in batches:
            keep, names = [], []
            for row, grams in _sets(batch.column(0), n):
                name = _name(grams)
                h = int.from_bytes(name[:8], "little") % MARKS
                if len(grams) and bits[h >> 3] >> (7 - (h & 7)) & 1 and name not in seen:
                    seen.add(name)
                    keep.append(row)
                    names.append(name)
            yield pa.RecordBatch.from_arrays([pa.array(names, pa.binary()), batch.column(0).take(pa.array(keep, pa.int64()))], names=["fp", "text"])

    def open_up(batches):
        for batch in batches:
            raw = [grams.tobytes() for _, grams in _sets(batch.column(1), n)]
            yield pa.RecordBatch.from_arrays([batch.column(0), pa.array(raw, pa.binary())], names=["fp", "grams"])

    found = docs.select(F.col(text).alias("text")).mapInArrow(find, "fp binary, text string").dropDuplicates(["fp"])
    return found.mapInArrow(open_up, "fp binary, grams binary")


def _forest(rows, count: int):
    """Yields (a, others, tree) for rows (a, others) of numbers below ``count``: tree holds those of the others that a
    spanning forest of all pairs needs."""
    if count <= 64:
        parent = list(range(count))

        def root(x):
            while parent[x] != x:
                parent[x] = parent[parent[x]]
                x = parent[x]
            return x

        for a, others in rows:
            tree = []
            for b in others.tolist():
                x, y = root(a), root(b)
                if x != y:
                    parent[y] = x
                    tree.append(b)
            yield a, others, np.array(tree, np.int64)
        return
    label = np.arange(count)
    for a, others in rows:
        labels, first = np.unique(label[others], return_index=True)
        new = labels != label[a]
        if new.any():
            label[np.isin(label, labels[new])] = label[a]
        yield a, others, others[first[new]]


def _edges(lists: DataFrame, column: str, width: int = FP_BYTES) -> DataFrame:
    """(a, b) from rows that hold the names b of one a end to end."""
    each = F.expr(f"transform(sequence(1, octet_length({column}), {width}), i -> substring({column}, i, {width}))")
    return lists.where(F.octet_length(column) > 0).select("a", F.explode(each).alias("b"))


def _grouped_in_one(batches):
    """(node, component) of all edges from a to each name in tree, at most ``EDGES`` of them: trees of names whose roots
    hook onto smaller neighbours, so each pass halves the number of trees that are not done."""
    left, right = [], []
    for batch in batches:
        for a, tree in zip(batch.column(0).to_pylist(), batch.column(1).to_pylist()):
            left.append(a * (len(tree) // FP_BYTES))
            right.append(tree)
    ends = np.frombuffer(b"".join(left + right), ">u8").astype(np.uint64).reshape(-1, FP_BYTES // 8)
    names, at = np.unique(ends, axis=0, return_inverse=True)
    a, b = at.reshape(2, -1)
    low = np.arange(len(names))
    while (apart := low[a] != low[b]).any():
        a, b = a[apart], b[apart]
        x, y = low[a], low[b]
        np.minimum.at(low, np.maximum(x, y), np.minimum(x, y))
        while ((further := low[low]) != low).any():
            low = further
    raw = names.astype(">u8").tobytes()
    each = [raw[k : k + FP_BYTES] for k in range(0, len(raw), FP_BYTES)]
    for lo in range(0, len(each), 1 << 16):
        own = each[lo : lo + (1 << 16)]
        yield pa.RecordBatch.from_arrays([pa.array(own, pa.binary()), pa.array([each[k] for k in low[lo : lo + len(own)].tolist()], pa.binary())], names=["node", "component"])


def _graph_groups(lists: DataFrame, scratch: Scratch) -> DataFrame:
    """(node, component) of the edges (a, each name in tree); component is the smallest name reachable.

    Rounds cost many tasks whatever the size, and the sorts and hash tables of each take their pages from the heap of
    the executor; so a graph of up to ``EDGES`` edges is grouped by one task, and only a larger one in rounds."""
    linked = lists.where(F.octet_length("tree") > 0).select("a", "tree")
    amount = linked.agg(F.sum(F.octet_length("tree").cast("bigint"))).first()[0] or 0
    if amount > EDGES * FP_BYTES:
        return scratch.put(components(_edges(linked, "tree"), "a", "b"), "op5-components")
    return scratch.put(linked.coalesce(1).mapInArrow(_grouped_in_one, "node binary, component binary"), "op5-components")


def _shared_columns(values: pa.Array, offsets: np.ndarray) -> tuple[int, np.ndarray, np.ndarray]:
    """The values that occur more than once between the offsets: how many, their numbers row by row, where rows start."""
    coded = values[offsets[0] : offsets[-1]].dictionary_encode()
    code = coded.indices.to_numpy()
    several = np.bincount(code, minlength=len(coded.dictionary)) > 1
    number = (np.cumsum(several) - 1).astype(np.int32)
    inside = several[code]
    start = np.zeros(len(code) + 1, np.int32)
    np.cumsum(inside, dtype=np.int32, out=start[1:])
    return int(several.sum()), number[code[inside]], start[offsets - offsets[0]].astype(np.int64)


def _pairs_in_lists(percent: int):
    """For each class of a list (or of two tiles of it) the partners that no filter can rule out, and those of them that
    a spanning forest needs. Rows come sorted by list and tiles."""

    def long_list(rows, same_tile: bool):
        size, place, tile, spreads, before = rows
        spread = np.stack(spreads)
        shared, column, start = _shared_columns(*before)
        stop, start = start[1:], start[:-1]
        left = np.flatnonzero(tile == tile[0])
        right = left if same_tile else np.flatnonzero(tile != tile[0])
        right = right[np.argsort(size[right], kind="stable")]
        # few shared columns: one product tests a row against all; many: the first columns of each row, then the rest of
        # those pairs that are left at the end
        dense = shared <= 256
        if dense:
            matrix = np.zeros((len(size), shared), np.float32)
            matrix[np.repeat(np.arange(len(size), dtype=np.int32), stop - start), column] = 1
        else:
            mark = np.zeros(shared + 1, bool)
            at = start[:, None] + np.arange(HEAD)
            head = np.where(at < stop[:, None], column[np.minimum(at, len(column) - 1)], shared)
        sorted_size = size[right]
        for a in left.tolist():
            lo = np.searchsorted(sorted_size, -(-percent * size[a] // 100), "left")
            hi = np.searchsorted(sorted_size, 100 * size[a] // percent, "right")
            other = right[lo:hi]
            if same_tile:
                other = other[other > a]
            if dense and len(other) and start[a] < stop[a]:
                other = other[matrix[other] @ matrix[a] == 0]
            if not len(other):
                continue
            need = -(-percent * (size[a] + size[other]) // (100 + percent))
            near = np.minimum(size[a] - place[a], size[other] - place[other]) >= need
            other, need = other[near], need[near]
            other = other[np.minimum(spread[a], spread[other]).sum(axis=1, dtype=np.int64) >= need]
            if not dense and len(other):
                mine = column[start[a] : stop[a]]
                mark[mine] = True
                other = other[~mark[head[other]].any(axis=1)]
                other = np.array([o for o in other.tolist() if not mark[column[start[o] + HEAD : stop[o]]].any()], np.int64)
                mark[mine] = False
            if len(other):
                yield a, other

    def short_list(rows, same_tile: bool):
        size, place, tile, spreads, (values, offsets) = rows
        size, place, tile = size.tolist(), place.tolist(), tile.tolist()
        before: list = [None] * len(size)
        for a in range(len(size) - 1):
            found = []
            for b in range(a + 1, len(size)):
                if same_tile == (tile[a] != tile[b]) or percent * max(size[a], size[b]) > 100 * min(size[a], size[b]):
                    continue
                need = -(-percent * (size[a] + size[b]) // (100 + percent))
                if min(size[a] - place[a], size[b] - place[b]) < need or int(np.minimum(spreads[a], spreads[b]).sum(dtype=np.int64)) < need:
                    continue
                for k in (a, b):
                    if before[k] is None:
                        before[k] = set(values[offsets[k] : offsets[k + 1]].to_pylist())
                if before[a].isdisjoint(before[b]):
                    found.append(b)
            if found:
                yield a, np.array(found, np.int64)

    def pairs_of(table):
        """Pairs of all lists in ``table``, whose lists are whole."""
        columns = {k: table.column(k).to_numpy() for k in ("token", "tile_a", "tile_b", "tile", "size", "place")}
        lists = np.stack([columns[k].astype(np.int64) for k in ("token", "tile_a", "tile_b")])
        cuts = [0, *(np.flatnonzero((lists[:, 1:] != lists[:, :-1]).any(axis=0)) + 1).tolist(), len(table)]
        before = table.column("before").combine_chunks()
        values, offsets = before.values, before.offsets.to_numpy()
        fps, spreads = table.column("fp").to_pylist(), table.column("spread").to_pylist()
        size, place, tile = columns["size"].astype(np.int64), columns["place"].astype(np.int64), columns["tile"]
        out: list[tuple[bytes, bytes, bytes]] = []
        held = 0
        for lo, hi in zip(cuts, cuts[1:]):
            if hi - lo < 2:
                continue
            rows = (
                size[lo:hi],
                place[lo:hi],
                tile[lo:hi],
                [np.frombuffer(x, np.uint8 if len(x) == BINS else np.uint32) for x in spreads[lo:hi]],
                (values, offsets[lo : hi + 1]),
            )
            short = np.array([fp[:NAME_BYTES] for fp in fps[lo:hi]], f"V{NAME_BYTES}")
            for a, others, tree in _forest((short_list if hi - lo <= SHORT else long_list)(rows, bool(lists[1, lo] == lists[2, lo])), hi - lo):
                out.append((fps[lo + a], short[others].tobytes(), b"".join(fps[lo + k] for k in tree.tolist())))
                held += len(others)
                if held > 1_000_000:
                    yield listed(out)
                    out, held = [], 0
        yield listed(out)

    def listed(out):
        return pa.RecordBatch.from_arrays([pa.array([x[k] for x in out], pa.binary()) for k in range(3)], names=["a", "partners", "tree"])

    def run(batches):
        rest = None
        for batch in batches:
            table = pa.Table.from_batches([batch])
            table = table if rest is None else pa.concat_tables([rest, table]).combine_chunks()
            # the last list may go on in the next batch; it is at most two tiles long
            last = [table.column(k)[-1].as_py() for k in ("token", "tile_a", "tile_b")] if len(table) else None
            if last is None:
                continue
            other = np.zeros(len(table), bool)
            for k, x in zip(("token", "tile_a", "tile_b"), last):
                other |= table.column(k).to_numpy() != x
            cut = int(np.flatnonzero(other)[-1]) + 1 if other.any() else 0
            rest = table.slice(cut)
            if cut:
                yield from pairs_of(table.slice(0, cut))
        if rest is not None and len(rest):
            yield from pairs_of(rest)

    return run


def candidate_pairs(rows: DataFrame, classes: DataFrame, percent: int, tile: int = TILE) -> DataFrame:
    """(a, b) short names of classes that share a prefix n-gram and pass every filter; each pair once."""
    return _edges(candidate_lists(rows, classes, percent, tile), "partners", NAME_BYTES).select(F.substring("a", 1, NAME_BYTES).alias("a"), "b")


def shared_prefixes(scanned: DataFrame, percent: int) -> DataFrame:
    """The prefix rows whose n-gram several classes show, with their number as ``length``."""
    return prefixes(scanned, percent).withColumn("length", F.count("*").over(Window.partitionBy("token"))).where("length > 1")


def candidate_lists(rows: DataFrame, classes: DataFrame, percent: int, tile: int = TILE) -> DataFrame:
    """The candidate pairs as (a, partners, tree): the short names of the partners of a, end to end, and the fingerprints
    of those that keep every family of candidates connected. Each pair is in one row."""
    # the part of a class's prefix that others show too, in its order; at most as long as the prefix
    shown = rows.groupBy("fp").agg(F.array_sort(F.collect_list(F.struct("place", "token"))).alias("s")).select("fp", F.transform("s", lambda x: x["token"]).alias("prefix"))
    traits = shown.join(classes.select("fp", "spread"), "fp")
    dealt = rows.withColumn("tiles", F.ceil(F.col("length") / tile).cast("int"))
    # each row goes to the tile pairs (i, j), i <= j, that contain its own tile
    dealt = dealt.withColumn("tile", F.pmod(F.xxhash64("fp"), F.col("tiles")).cast("int")).withColumn("with", F.explode(F.expr("sequence(0, tiles - 1)")))
    dealt = dealt.select("token", F.least("tile", "with").alias("tile_a"), F.greatest("tile", "with").alias("tile_b"), "tile", "fp", "place", "size")
    # the shared n-grams of a class before this one tell where else its pairs are looked at
    told = dealt.join(traits, "fp").withColumn("before", F.expr("slice(prefix, 1, CAST(array_position(prefix, token) AS INT) - 1)")).drop("prefix")
    lists = told.repartition("token", "tile_a", "tile_b").sortWithinPartitions("token", "tile_a", "tile_b")
    return lists.select("token", "tile_a", "tile_b", "tile", "fp", "place", "size", "before", "spread").mapInArrow(_pairs_in_lists(percent), "a binary, partners binary, tree binary")


def _tile_of(names: np.ndarray, tiles: int) -> np.ndarray:
    return (V.mix(names.view("<u8").astype(np.uint64)) % np.uint64(tiles)).astype(np.int64)


def _place(tile: int):
    """Candidates as (family, tile_a, tile_b, a, partners): the partners of a that lie in one tile; both as short names."""

    def run(batches):
        for batch in batches:
            out: list[tuple] = []
            for a, partners, family, members in zip(*(batch.column(k).to_pylist() for k in range(4))):
                tiles = -(-members // tile)
                a = a[:NAME_BYTES]
                if tiles == 1:
                    out.append((family, 0, 0, a, partners))
                    continue
                names = np.frombuffer(partners, f"V{NAME_BYTES}")
                own, other = int(_tile_of(np.frombuffer(a, f"V{NAME_BYTES}"), tiles)[0]), _tile_of(names, tiles)
                for t in np.unique(other).tolist():
                    out.append((family, min(own, t), max(own, t), a, names[other == t].tobytes()))
            kinds = [pa.binary(), pa.int32(), pa.int32(), pa.binary(), pa.binary()]
            yield pa.RecordBatch.from_arrays([pa.array([x[k] for x in out], kind) for k, kind in enumerate(kinds)], names=["family", "tile_a", "tile_b", "a", "partners"])

    return run


def _ends(batches):
    """(family, tile_a, tile_b, name) of the classes that each tile pair needs; one row per class of a task and tile pair."""
    seen: dict[tuple, set[bytes]] = {}
    for batch in batches:
        out = []
        for *key, a, partners in zip(*(batch.column(k).to_pylist() for k in range(5))):
            known = seen.setdefault(tuple(key), set())
            new = {a, *(partners[k : k + NAME_BYTES] for k in range(0, len(partners), NAME_BYTES))} - known
            known |= new
            out += [(*key, name) for name in new]
        kinds = [pa.binary(), pa.int32(), pa.int32(), pa.binary()]
        yield pa.RecordBatch.from_arrays([pa.array([x[k] for x in out], kind) for k, kind in enumerate(kinds)], names=["family", "tile_a", "tile_b", "name"])
        if sum(map(len, seen.values())) > 500_000:
            seen = {}


def _views(column: pa.ChunkedArray) -> list[np.ndarray]:
    """The numbers in each binary value, where they lie."""
    out = []
    for chunk in column.chunks:
        _, at, raw = chunk.buffers()
        at = np.frombuffer(at, np.int64 if pa.types.is_large_binary(chunk.type) else np.int32)[chunk.offset : chunk.offset + len(chunk) + 1].tolist()
        raw = np.frombuffer(raw, np.uint8) if raw else np.zeros(0, np.uint8)
        out += [raw[lo:hi].view(np.uint64) for lo, hi in zip(at, at[1:])]
    return out


def _common(grams: list[np.ndarray], a: np.ndarray, b: np.ndarray) -> np.ndarray:
    """Common n-grams of the sets of each pair (a, b). Where most pairs of a tile are asked for, by products of matrices."""
    left, right = np.unique(a), np.unique(b)
    if len(a) < 256 or 16 * len(a) < len(left) * len(right):
        out = np.zeros(len(a), np.int64)
        for k, (x, y) in enumerate(zip(a.tolist(), b.tolist())):
            both = np.concatenate([grams[x], grams[y]])
            both.sort()
            out[k] = (both[1:] == both[:-1]).sum()
        return out
    used = np.unique(np.concatenate([left, right]))
    bounds = np.cumsum([0, *(len(grams[k]) for k in used)])
    _, column, start = _shared_columns(pa.array(np.concatenate([grams[k] for k in used])), bounds)
    owner = np.repeat(used.astype(np.int32), np.diff(start))
    order = np.argsort(column, kind="stable")
    owner, column = owner[order], column[order]
    total = np.zeros((len(left), len(right)), np.float32)
    row_l, row_r = np.full(len(grams), -1), np.full(len(grams), -1)
    row_l[left], row_r[right] = np.arange(len(left)), np.arange(len(right))
    width = 4096
    for first in range(0, int(column[-1]) + 1 if len(column) else 0, width):
        lo, hi = np.searchsorted(column, [first, first + width])
        sides = []
        for place, count in ((row_l, len(left)), (row_r, len(right))):
            side = np.zeros((count, width), np.float32)
            at = place[owner[lo:hi]]
            side[at[at >= 0], column[lo:hi][at >= 0] - first] = 1
            sides.append(side)
        total += sides[0] @ sides[1].T
    return total[row_l[a], row_r[b]].astype(np.int64)


def verify(candidates: DataFrame, docs: DataFrame, classes: DataFrame, percent: int, text: str, n: int, scratch: Scratch, tile: int = 1024) -> DataFrame:
    """(a, others, tree) of what links, checked once per pair against whole sets: the documents that a links with in
    other classes (several rows of one a add up), and the partners that keep every group connected.

    Pairs are checked family by family (a component of the candidate graph), large families tile by tile: a set
    travels once per tile pair it is needed in and not once per pair, and no row per pair is made.
    """
    groups = _graph_groups(candidates, scratch)
    family = groups.withColumnRenamed("component", "family")
    size = family.groupBy("family").agg(F.count("*").alias("members"))
    family = scratch.put(family.join(size, "family").select(F.col("node").alias("a"), "family", "members"), "op5-families")
    scratch.drop(groups)
    placed = candidates.select("a", "partners").join(family, "a").select("a", "partners", "family", "members")
    placed = scratch.put(placed.mapInArrow(_place(tile), "family binary, tile_a int, tile_b int, a binary, partners binary"), "op5-placed")
    scratch.drop(candidates)
    ends = placed.mapInArrow(_ends, "family binary, tile_a int, tile_b int, name binary").distinct()
    member = family.select("family", F.col("a").alias("fp"), F.substring("a", 1, NAME_BYTES).alias("name"))
    needed = ends.join(member, ["family", "name"])
    held = needed.join(_wanted_sets(docs, member, text, n), "fp").join(classes.select("fp", "copies"), "fp")

    def run(key, left, right):
        fps = right.column("fp").to_pylist()
        grams = _views(right.column("grams"))
        size = np.array([len(g) for g in grams], np.int64)
        copies = right.column("copies").to_numpy().astype(np.int64)
        names = np.array([int.from_bytes(fp[:NAME_BYTES], "little") for fp in fps], np.uint64)
        order = np.argsort(names)
        partners = left.column("partners").to_pylist()
        a = np.repeat(np.array([int.from_bytes(x, "little") for x in left.column("a").to_pylist()], np.uint64), [len(x) // NAME_BYTES for x in partners])
        a, b = (order[np.searchsorted(names[order], x)] for x in (a, np.frombuffer(b"".join(partners), "<u8")))
        # the product needs one tile on each side; within a tile any order of a pair does
        inter = np.zeros(len(a), np.int64)
        for lo in range(0, len(a), 1 << 21):
            inter[lo : lo + (1 << 21)] = _common(grams, a[lo : lo + (1 << 21)], b[lo : lo + (1 << 21)])
        linked = 100 * inter >= percent * (size[a] + size[b] - inter)
        a, b = a[linked], b[linked]
        others = np.zeros(len(fps), np.int64)
        np.add.at(others, a, copies[b])
        np.add.at(others, b, copies[a])
        order = np.argsort(a, kind="stable")
        a, b = a[order], b[order]
        starts = np.flatnonzero(np.diff(a, prepend=-1)) if len(a) else np.zeros(0, np.int64)
        trees = {x: b"".join(fps[k] for k in tree.tolist()) for x, _, tree in _forest(((int(a[lo]), b[lo:hi]) for lo, hi in zip(starts, [*starts[1:], len(a)])), len(fps))}
        has = np.flatnonzero(others).tolist()
        return pa.table({"a": pa.array([fps[k] for k in has], pa.binary()), "others": pa.array(others[has], pa.int64()), "tree": pa.array([trees.get(k, b"") for k in has], pa.binary())})

    held = held.select(F.col("family").alias("f"), F.col("tile_a").alias("i"), F.col("tile_b").alias("j"), "fp", "grams", "copies")
    return placed.groupBy("family", "tile_a", "tile_b").cogroup(held.groupBy("f", "i", "j")).applyInArrow(run, "a binary, others bigint, tree binary")


def grouped_classes(docs: DataFrame, doc_id: str, text: str, n: int, percent: int, scratch: Scratch) -> tuple[DataFrame, DataFrame]:
    """(doc_id, fp, n_shingles, salt) of all rows, and (fp, low, copies, component, others) of all classes with n-grams."""
    scanned = scratch.put(scan(docs, _pieces(docs, text), doc_id, text, n), "op5-scan")
    rows = scratch.put(shared_prefixes(scanned, percent), "op5-prefixes")
    own = scanned.where(F.col("kind") == DOC)
    salt = F.pmod(F.xxhash64("doc_id"), F.lit(SALTS)).cast("int").alias("salt")
    sets = scratch.put(own.select("doc_id", "fp", "n_shingles", salt), "op5-sets")
    # copies are counted part by part first
    parts = own.where("n_shingles > 0").groupBy("fp", salt).agg(F.min("doc_id").alias("low"), F.count("*").alias("copies"), F.first("spread").alias("spread"))
    classes = scratch.put(parts.groupBy("fp").agg(F.min("low").alias("low"), F.sum("copies").alias("copies"), F.first("spread").alias("spread")), "op5-copies")
    scratch.drop(scanned)
    candidates = scratch.put(candidate_lists(rows, classes, percent), "op5-pairs")
    scratch.drop(rows)
    links = scratch.put(verify(candidates, docs, classes, percent, text, n, scratch), "op5-links")
    groups = _graph_groups(links, scratch)
    found = groups.withColumnRenamed("node", "fp")
    degree = links.groupBy(F.col("a").alias("fp")).agg(F.sum("others").alias("others"))
    grouped = classes.drop("spread").join(found, "fp", "left").join(degree, "fp", "left")
    grouped = scratch.put(grouped.select("fp", "low", "copies", F.coalesce("component", "fp").alias("component"), F.coalesce("others", F.lit(0)).alias("others")), "op5-classes")
    scratch.drop(links, classes, groups)
    return sets, grouped


def jaccard_groups(docs: DataFrame, doc_id: str = "doc_id", text: str = "text", n: int = 3, percent: int = 90) -> DataFrame:
    """One row per document: doc_id, n_shingles, component_id and n_links (documents it links with, copies included)."""
    bounded_batches(docs.sparkSession)
    sets, grouped = grouped_classes(docs, doc_id, text, n, percent, Scratch(docs.sparkSession))
    # a class is named by its fingerprint while labels travel, then every component takes its smallest document
    lowest = grouped.groupBy("component").agg(F.min("low").alias("component_id"))
    named = grouped.join(lowest, "component").select("fp", "component_id", (F.col("copies") - 1 + F.col("others")).alias("n_links"))
    # a class of many copies meets its documents in as many parts as they were dealt to
    parts = sets.where("n_shingles > 0").select("fp", "salt").distinct().join(named, "fp")
    filled = F.col("n_shingles") > 0
    return (
        sets.join(parts, ["fp", "salt"], "left")
        .select("doc_id", "n_shingles", F.when(filled, F.col("component_id")).otherwise(F.col("doc_id")).alias("component_id"), F.when(filled, F.col("n_links")).otherwise(F.lit(0)).cast("bigint").alias("n_links"))
    )


def keep_one_per_group(docs: DataFrame, n: int = 5, percent: int = 80) -> DataFrame:
    """``docs`` with one row of each near-duplicate group: of the texts in it that with the smallest doc_id, and one row of
    that text. Rows that share a doc_id but not a text are judged each by its own text; texts without words all stay."""
    scratch = Scratch(docs.sparkSession)
    bounded_batches(docs.sparkSession)
    _, grouped = grouped_classes(docs, "doc_id", "text", n, percent, scratch)
    first = grouped.groupBy("component").agg(F.min_by(F.struct("fp", "low"), F.struct(F.col("low").isNull(), "low", "fp")).alias("x")).select("x.*")
    fp, who, kept, rank = free_names(docs, "fp", "who", "kept", "rank")
    spelled = lambda c: F.coalesce(F.concat(F.lit("="), c.cast("string")), F.lit("-"))
    chosen = first.select(F.col("fp").alias(fp), spelled(F.col("low")).alias(who), F.lit(True).alias(kept))

    @F.arrow_udf("binary")
    def name(texts: pa.Array) -> pa.Array:
        return pa.array([_name(grams) if len(grams) else None for _, grams in _sets(texts, n)], pa.binary())

    # rows meet by text and id, so copies of one text go to as many tasks as they have ids
    tagged = docs.withColumn(fp, name("text")).withColumn(who, spelled(F.col("doc_id")))
    met = tagged.join(chosen, [fp, who], "left").withColumn(rank, F.row_number().over(Window.partitionBy(fp, who).orderBy(F.xxhash64(*docs.columns))))
    return met.where(F.col(fp).isNull() | (F.col(kept) & (F.col(rank) == 1))).select(*(F.col(f"`{c}`") for c in docs.columns))


def op5_ngram_jaccard_join(spark, sf_dir: str) -> DataFrame:
    return jaccard_groups(spark.read.parquet(f"{sf_dir}/documents.parquet"))


SQL = r"""
WITH RECURSIVE d AS (SELECT doc_id, row_number() OVER () AS r, regexp_extract_all(translate(coalesce(text, ''), 'ABCDEFGHIJKLMNOPQRSTUVWXYZ', 'abcdefghijklmnopqrstuvwxyz'), '[^\x20\x09-\x0D]+') AS w FROM documents),
s AS (SELECT doc_id, r, CASE WHEN len(w) = 0 THEN [] WHEN len(w) < 3 THEN [array_to_string(w, ' ')] ELSE list_distinct(list_transform(range(1, len(w) - 1), lambda i: array_to_string(w[i:i + 2], ' '))) END AS g FROM d),
e AS (SELECT r, len(g) AS n, unnest(g) AS x FROM s),
pairs AS (SELECT a.r AS p, b.r AS q, a.n AS pn, b.n AS qn, count(*) AS i FROM e a JOIN e b ON a.x = b.x AND a.r < b.r AND 10 * a.n >= 9 * b.n AND 10 * b.n >= 9 * a.n GROUP BY ALL),
l AS (SELECT a.doc_id AS p, b.doc_id AS q FROM pairs JOIN s a ON a.r = p JOIN s b ON b.r = q WHERE 100 * i >= 90 * (pn + qn - i)),
both_ways AS (SELECT p, q FROM l UNION SELECT q, p FROM l),
reach(node, far) AS (SELECT doc_id, doc_id FROM s UNION SELECT reach.node, both_ways.q FROM reach JOIN both_ways ON reach.far = both_ways.p)
SELECT s.doc_id, len(g)::BIGINT AS n_shingles, c.component_id, coalesce(k.n, 0)::BIGINT AS n_links
FROM s JOIN (SELECT node, min(far) AS component_id FROM reach GROUP BY node) c ON c.node = s.doc_id LEFT JOIN (SELECT p, count(*) AS n FROM both_ways GROUP BY p) k ON k.p = s.doc_id
"""
