"""Best-fit packing by bin completion with branch and bound.

Texts become token ids, each document one row of pieces: ``capacity`` ids at most, the remainder first. The pieces are
dealt into groups of bounded size and each group is packed on its own. In a group the largest open piece starts a bin;
the search enumerates the undominated fillings of the room it leaves (nothing that is open still fits, no piece can be
swapped for a larger one, no two pieces for a single one), prunes those that waste more than one bin fewer than the
incumbent leaves, and keeps the best-fit-decreasing solution as incumbent until a better one is complete. The search of
a group ends when it is exhausted, when it reaches a lower bound, or after ``NODES`` fillings (plus one a piece).

Nulls and edge cases: a null text is an empty one and holds only the end id; ids repeat freely, each row is packed;
texts of any length are cut, never dropped; extra columns are ignored; an empty table gives an empty result.
"""

from __future__ import annotations

import itertools
import json
import re
import zlib
from bisect import bisect_left, bisect_right, insort

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from .common import bounded_batches, stored

CAPACITY = 2048
GROUP_PIECES = 16384
#: Nodes the search may open in one group before it settles for the incumbent.
NODES = 20_000
CACHED_WORDS = 400_000

# characters for which the fast splitter below and the tokenizer's own agree: ASCII text and Latin letters
_UNSAFE = re.compile(r"[^\t\n\r -~À-ÖØ-öø-ɏ]")
_SPLIT = re.compile(r"'(?:s|t|re|ve|m|ll|d)| ?[A-Za-zÀ-ÖØ-öø-ɏ]+| ?[0-9]+| ?[^\sA-Za-zÀ-ÖØ-öø-ɏ0-9]+|\s+(?!\S)|\s+")
_loaded: dict = {}


def _byte_signs() -> dict[int, str]:
    """The sign by which a byte-level vocabulary writes each byte: printable Latin-1 as it is, the others in order from 256."""
    plain = {*range(0x21, 0x7F), *range(0xA1, 0xAD), *range(0xAE, 0x100)}
    others = iter(range(0x100, 0x200))
    return {b: chr(b if b in plain else next(others)) for b in range(256)}


class _Words(dict):
    """Ids of words seen lately, as bytes; a missing word is encoded, or taken from those seen before: bounded, and words
    in use stay."""

    def __init__(self, tokenizer):
        self.older: dict[str, bytes] = {}
        signs = _byte_signs()
        letters = {c: "".join(signs[b] for b in chr(c).encode()) for c in range(0x250)}
        tokenize = tokenizer.model.tokenize

        def bare(word: str) -> bytes:
            return np.array([t.id for t in tokenize(word.translate(letters))], "<u4").tobytes()

        def whole(word: str) -> bytes:
            return np.array(tokenizer.encode(word, add_special_tokens=False).ids, "<u4").tobytes()

        # a word of the splitter is one piece for the model, unless the tokenizer changes text before
        step = json.loads(tokenizer.to_str())
        before = step.get("pre_tokenizer") or {}
        plain = step.get("normalizer") is None and before.get("type") == "ByteLevel" and not before.get("add_prefix_space")
        self.encode = bare if plain and step["model"].get("type") == "BPE" and not step["model"].get("dropout") else whole

    def __missing__(self, word: str) -> bytes:
        found = self.older.get(word)
        if found is None:
            found = self.encode(word)
        self[word] = found
        return found

    def turn(self) -> None:
        if len(self) > CACHED_WORDS:
            self.older = dict(self)
            self.clear()


def _tokenizer(path: str):
    """The tokenizer and its words."""
    if path not in _loaded:
        import os

        os.environ["TOKENIZERS_PARALLELISM"] = "false"
        from tokenizers import Tokenizer

        _loaded.clear()
        tokenizer = Tokenizer.from_file(path)
        _loaded[path] = (tokenizer, _Words(tokenizer))
    return _loaded[path]


def token_bytes(texts: list[str | None], path: str) -> list[bytes]:
    """Ids of each text as little-endian 32-bit numbers. Words seen before come from a bounded cache."""
    tokenizer, words = _tokenizer(path)
    whole: dict[int, str] = {}
    out = [b""] * len(texts)
    ids_of = words.__getitem__
    for k, text in enumerate(texts):
        if not text:
            continue
        if _UNSAFE.search(text) or "<|" in text:
            whole[k] = text
        else:
            out[k] = b"".join(map(ids_of, _SPLIT.findall(text)))
            words.turn()
    if whole:
        for k, e in zip(whole, tokenizer.encode_batch(list(whole.values()), add_special_tokens=False)):
            out[k] = np.array(e.ids, "<u4").tobytes()
    return out


def pieces(docs: DataFrame, tokenizer_path: str, doc_id: str = "doc_id", text: str = "text", capacity: int = CAPACITY, end_id: int = 0) -> DataFrame:
    """(doc_id, piece, start, length, ids_crc32), in no order."""
    kind = docs.schema[doc_id].dataType.simpleString()

    def run(batches):
        end = int(end_id).to_bytes(4, "little")
        for batch in batches:
            for at in range(0, batch.num_rows, 256):
                part = batch.slice(at, 256)
                source, piece, start, length, crc = [], [], [], [], []
                for k, raw in enumerate(token_bytes(part.column(1).to_pylist(), tokenizer_path)):
                    raw += end
                    n = len(raw) // 4
                    first = n % capacity or capacity
                    a, p = 0, 0
                    while a < n:
                        b = first if not p else a + capacity
                        source.append(k)
                        piece.append(p)
                        start.append(a)
                        length.append(b - a)
                        crc.append(zlib.crc32(raw[4 * a : 4 * b]))
                        a, p = b, p + 1
                yield pa.RecordBatch.from_arrays(
                    [part.column(0).take(pa.array(source, pa.int64())), pa.array(piece, pa.int32()), *(pa.array(x, pa.int64()) for x in (start, length, crc))],
                    names=["doc_id", "piece", "start", "length", "ids_crc32"],
                )

    return docs.select(F.col(doc_id).alias("doc_id"), text).mapInArrow(run, f"doc_id {kind}, piece int, start bigint, length bigint, ids_crc32 bigint")


def best_fit(sizes: list[int], capacity: int) -> list[list[int]]:
    """Best-fit decreasing: bins of positions."""
    rooms: list[tuple[int, int]] = []
    bins: list[list[int]] = []
    for k in sorted(range(len(sizes)), key=lambda k: -sizes[k]):
        at = bisect_left(rooms, (sizes[k], -1))
        if at < len(rooms):
            room, b = rooms.pop(at)
        else:
            room, b = capacity, len(bins)
            bins.append([])
        bins[b].append(k)
        if room > sizes[k]:
            insort(rooms, (room - sizes[k], b))
    return bins


def undominated(chosen: list[int], left: int, kinds: list[int], counts: dict[int, int], used: dict[int, int]) -> bool:
    """Whether no other filling is at least as good whatever comes after: nothing open still fits, no piece can be
    swapped for a larger open one, and no two pieces for a single open one that takes their place."""
    for size in kinds:
        if size > left:
            break
        if counts[size] > used.get(size, 0):
            return False

    def open_from(size: int, most: int) -> bool:
        at = bisect_left(kinds, size)
        while at < len(kinds) and kinds[at] <= most:
            if counts[kinds[at]] > used.get(kinds[at], 0):
                return True
            at += 1
        return False

    distinct = sorted(set(chosen))
    if any(open_from(s + 1, s + left) for s in distinct):
        return False
    for i, a in enumerate(distinct):
        for b in distinct[i:]:
            if (a != b or used[a] > 1) and open_from(a + b, a + b + left):
                return False
    return True


def fillings(kinds: list[int], counts: dict[int, int], room: int, waste: int):
    """The undominated fillings of ``room`` that waste at most ``waste``, largest pieces first; None for each other
    filling looked at. All are reached in the end: only the caller stops the search.

    Between two steps the caller may change ``kinds`` and ``counts``, if they are back as they were for the next.
    """
    chosen: list[int] = []
    used: dict[int, int] = {}
    left = top = room
    while True:
        while True:
            at = bisect_right(kinds, min(left, top)) - 1
            while at >= 0 and counts[kinds[at]] <= used.get(kinds[at], 0):
                at -= 1
            if at < 0:
                break
            size = kinds[at]
            chosen.append(size)
            used[size] = used.get(size, 0) + 1
            left -= size
            top = size
        good = left <= waste and undominated(chosen, left, kinds, counts, used)
        yield (left, tuple(chosen)) if good else None
        if not chosen:
            return
        size = chosen.pop()
        used[size] -= 1
        left += size
        top = size - 1


def _fullest_first(found, every: int = 16):
    """The same fillings, each ``every`` of them sorted by waste."""
    while True:
        some = list(itertools.islice(found, every))
        yield from sorted((x for x in some if x is not None), key=lambda x: x[0])
        yield from (x for x in some if x is None)
        if len(some) < every:
            return


def lower_bound(sizes: list[int], capacity: int) -> int:
    """Bins that any packing needs: for each size k, pieces over capacity - k share no bin with pieces of k or more."""
    ordered = sorted(sizes)
    sums = np.concatenate([[0], np.cumsum(ordered)])
    best = -(-int(sums[-1]) // capacity)
    half = bisect_right(ordered, capacity // 2)
    for k in sorted({s for s in ordered[:half]}):
        low, high = bisect_left(ordered, k), bisect_right(ordered, capacity - k)
        alone, large = len(ordered) - high, high - half
        middle = int(sums[half] - sums[low])
        rest = middle - (large * capacity - int(sums[high] - sums[half]))
        best = max(best, alone + large + max(0, -(-rest // capacity)))
    return best


def _complete(sizes: list[int], capacity: int, bins: int, nodes: int) -> tuple[list[tuple[int, ...]] | None, int]:
    """A packing into at most ``bins`` bins as sizes, or None if there is none or ``nodes`` are spent; fillings looked at."""
    counts: dict[int, int] = {}
    for s in sizes:
        counts[s] = counts.get(s, 0) + 1
    kinds = sorted(counts)

    def take(size: int) -> None:
        counts[size] -= 1
        if not counts[size]:
            kinds.pop(bisect_left(kinds, size))

    def give(size: int) -> None:
        if not counts[size]:
            insort(kinds, size)
        counts[size] += 1

    # an explicit stack, one entry per bin: its largest piece, its untried fillings, and waste and pieces of the present one
    stack: list[list] = []
    waste_now, opened, allowed = 0, 0, bins * capacity - sum(sizes)

    def open_bin() -> None:
        largest = kinds[-1]
        take(largest)
        stack.append([largest, _fullest_first(fillings(kinds, counts, capacity - largest, allowed - waste_now)), 0, ()])

    open_bin()
    while stack and opened < nodes:
        top = stack[-1]
        for size in top[3]:
            give(size)
        waste_now -= top[2]
        top[2], top[3] = 0, ()
        step = next(top[1], ())
        opened += 1
        if step is None:
            continue
        if not step:
            give(top[0])
            stack.pop()
            continue
        top[2], top[3] = step
        waste_now += step[0]
        for size in step[1]:
            take(size)
        if not kinds:
            return [(x[0], *x[3]) for x in stack], opened
        open_bin()
    return None, opened


def bin_completion(sizes: list[int], capacity: int = CAPACITY, nodes: int = NODES) -> list[list[int]]:
    """Bins of positions into ``sizes``; never more bins than best-fit decreasing gives, and the fewest there are if the
    search ends within ``nodes`` and one a piece."""
    incumbent = best_fit(sizes, capacity)
    least, left = lower_bound(sizes, capacity), nodes + len(sizes)
    while len(incumbent) > least and left > 0:
        best, opened = _complete(sizes, capacity, len(incumbent) - 1, left)
        left -= opened
        if best is None:
            break
        places: dict[int, list[int]] = {}
        for k, s in enumerate(sizes):
            places.setdefault(s, []).append(k)
        incumbent = [[places[s].pop() for s in b] for b in best]
    return incumbent


def pack(rows: DataFrame, capacity: int = CAPACITY, group_pieces: int = GROUP_PIECES) -> DataFrame:
    """Adds sequence_id and offset to rows that have a length. Full pieces need no search and pack alone."""
    n = rows.count()
    groups = max(1, -(-n // group_pieces))
    kind = rows.schema["doc_id"].dataType.simpleString()

    def run(key, table):
        group = int(key[0].as_py())
        table = table.drop_columns(["group"]).sort_by([("length", "descending"), ("ids_crc32", "ascending"), ("doc_id", "ascending"), ("piece", "ascending")])
        sizes = table.column("length").to_pylist()
        sequence, offset = np.zeros(len(sizes), np.int64), np.zeros(len(sizes), np.int64)
        for b, bin_ in enumerate(bin_completion(sizes, capacity)):
            at = 0
            for k in bin_:
                sequence[k], offset[k] = (group << 32) | b, at
                at += sizes[k]
        return table.append_column("sequence_id", pa.array(sequence)).append_column("offset", pa.array(offset))

    dealt = rows.withColumn("group", F.pmod(F.xxhash64("doc_id", "piece", "start", "length", "ids_crc32", F.monotonically_increasing_id()), F.lit(groups)))
    return dealt.groupBy("group").applyInArrow(run, f"doc_id {kind}, piece int, start bigint, length bigint, ids_crc32 bigint, sequence_id bigint, offset bigint")


def default_tokenizer() -> str:
    import public_tokenizers

    return str(public_tokenizers.path("byte_bpe_50k.json"))


def pack_documents(docs: DataFrame, tokenizer_path: str | None = None, capacity: int = CAPACITY) -> DataFrame:
    """doc_id, piece, start, length, ids_crc32, sequence_id and offset of every piece of every document."""
    return pack(stored(pieces(docs, tokenizer_path or default_tokenizer(), capacity=capacity), "op7-pieces"), capacity)


def op7_bin_completion_packing(spark, sf_dir: str) -> DataFrame:
    bounded_batches(spark)
    return pack_documents(spark.read.parquet(f"{sf_dir}/documents.parquet"))
