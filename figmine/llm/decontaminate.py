"""Benchmark decontamination by Wu-Manber multi-pattern search over words.

Patterns are the windows of the benchmark items: ``window`` consecutive words, or all words of a shorter item.
Windows of one length form a class. For a class of length L the search reads blocks of B = min(2, L) words:

* the shift table gives for each block of any pattern how far away the nearest possible end of a pattern is; a block
  outside the table lets the search jump L - B + 1 words, so clean text is probed at every (L - B + 1)-th word only.
  The words are cut into stretches of that length and all stretches jump side by side, each by its own shifts;
* where the shift is 0, the patterns in the bucket of the suffix hash are selected;
* each pattern of the bucket is compared with the text word by word, as bytes.

Nulls and edge cases: a null or empty text has no words and is never hit; an item without words has no window; a
null item_id still marks words but is not listed; repeated items count once; repeated documents give a row each;
extra columns pass through, and a given column with the name of a result column is replaced by it (removal keeps all
given columns as they were). The benchmark is read in blocks of at most ``block_words`` words (a longer item is a
block of its own), each broadcast after that check. A worker holds one block: what a block finds is written before the
next block is searched.
"""

from __future__ import annotations

import itertools
import re
from collections import defaultdict

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from . import textvec as V
from .common import bounded_batches, free_names, stored

WORD = re.compile(r"[^\x00-\x2F\x3A-\x60\x7B-\x7F]+")
_LOWER = str.maketrans("ABCDEFGHIJKLMNOPQRSTUVWXYZ", "abcdefghijklmnopqrstuvwxyz")
_LOWER_BYTES = bytes(b + 32 if 65 <= b <= 90 else b for b in range(256))


class WindowClass:
    """Shift table, suffix buckets and patterns of one length."""

    def __init__(self, length: int, patterns: dict[bytes, set]):
        self.length, self.block = length, min(2, length)
        self.reach = length - self.block + 1
        self.patterns = list(patterns.items())
        shift: dict[int, int] = {}
        buckets: dict[int, list[int]] = defaultdict(list)
        for k, (pattern, _) in enumerate(self.patterns):
            hashes = np.array([V.hash_word(w.decode()) for w in pattern.split(b" ")], np.uint64)
            blocks = self.blocks(hashes)
            for at, b in enumerate(map(int, blocks)):
                shift[b] = min(shift.get(b, length), len(blocks) - 1 - at)
            buckets[int(blocks[-1])].append(k)
        self.known = np.array(sorted(shift), np.uint64)
        self.shift = np.array([shift[int(b)] for b in self.known], np.int32)
        self.buckets = dict(buckets)

    def blocks(self, hashes: np.ndarray) -> np.ndarray:
        if self.block == 1:
            return hashes
        return V.mix(hashes[:-1] * np.uint64(3) + hashes[1:])

    def ends(self, hashes: np.ndarray) -> np.ndarray:
        """Block positions at which a pattern may end, over the words of several texts."""
        at = np.arange(self.reach - 1, len(hashes) - self.block + 1, self.reach)
        stop = np.minimum(at + self.reach, len(hashes) - self.block + 1)
        found = [np.zeros(0, np.int64)]
        while len(at):
            head = hashes[at] if self.block == 1 else V.mix(hashes[at] * np.uint64(3) + hashes[at + 1])
            place = V.position_of(self.known, head)
            shift = np.where(place >= 0, self.shift[place], self.reach)
            found.append(at[shift == 0])
            at = at + np.maximum(shift, 1)
            at, stop = at[at < stop], stop[at < stop]
        return np.sort(np.concatenate(found))


class PatternIndex:
    def __init__(self, items: list[tuple], window: int = 10):
        classes: dict[int, dict[bytes, set]] = defaultdict(lambda: defaultdict(set))
        for item_id, text in items:
            words = WORD.findall((text or "").translate(_LOWER))
            size = min(window, len(words))
            for at in range(len(words) - size + 1) if words else ():
                classes[size][" ".join(words[at : at + size]).encode()].add(item_id)
        self.classes = [WindowClass(n, p) for n, p in sorted(classes.items())]

    def search(self, step: V.Step) -> tuple[np.ndarray, np.ndarray, list[list[int]], list[set]]:
        """Words per text, hit words as spans per text, and items per text."""
        start, end, first = step.words(V.NON_WORD)
        hashes = step.span_hash(start, end)
        n = len(first) - 1
        spans: list[list[int]] = [[] for _ in range(n)]
        items: list[set] = [set() for _ in range(n)]
        data = step.data
        for c in self.classes:
            for e in c.ends(hashes):
                a = int(e) + c.block - c.length
                text = int(np.searchsorted(first, a, "right")) - 1
                if a + c.length > first[text + 1]:
                    continue
                tail = hashes[e] if c.block == 1 else V.mix(hashes[e : e + 1] * np.uint64(3) + hashes[e + 1 : e + 2])[0]
                said = None
                for k in c.buckets[int(tail)]:
                    pattern, owners = c.patterns[k]
                    if said is None:
                        said = b" ".join(
                            data[start[w] : end[w]].tobytes().translate(_LOWER_BYTES) for w in range(a, a + c.length)
                        )
                    if said == pattern:
                        spans[text] += [a - int(first[text]), a - int(first[text]) + c.length]
                        items[text] |= owners
        return np.diff(first), hashes, spans, items


def _blocks(benchmark: DataFrame, item_id: str, text: str, block_words: int):
    """The items in lists of at most ``block_words`` words (a longer item makes a list of its own)."""
    block, size = [], 0
    for row in benchmark.select(item_id, text).where(F.col(text).isNotNull()).distinct().toLocalIterator():
        words = len(WORD.findall(row[1].translate(_LOWER)))
        if block and size + words > block_words:
            yield block
            block, size = [], 0
        block.append((row[0], row[1]))
        size += words
    if block:
        yield block


def _pass(broadcast, text: str, names: list[str], first: bool):
    def run(batches):
        index = PatternIndex(*broadcast.value)
        for batch in batches:
            n_words, spans, items = [], [], []
            for _, step in V.steps(batch.column(batch.schema.names.index(text))):
                n, _, s, i = index.search(step)
                n_words += n.tolist()
                spans += s
                items += i
            items = [{str(x) for x in y if x is not None} for y in items]
            given = batch.select([c for c in batch.schema.names if c not in names])
            if not first:
                spans = [x + y for x, y in zip(spans, batch.column(batch.schema.names.index(names[1])).to_pylist())]
                items = [x | set(y) for x, y in zip(items, batch.column(batch.schema.names.index(names[2])).to_pylist())]
            yield pa.RecordBatch.from_arrays(
                [*given.columns, pa.array(n_words, pa.int64()), pa.array([_union(s) for s in spans], pa.list_(pa.int32())), pa.array([sorted(x) for x in items], pa.list_(pa.string()))],
                names=[*given.schema.names, *names],
            )

    return run


def _union(flat: list[int]) -> list[int]:
    """Overlapping [start, end) word spans made disjoint."""
    out: list[int] = []
    for a, b in sorted(zip(flat[::2], flat[1::2])):
        if out and a <= out[-1]:
            out[-1] = max(out[-1], b)
        else:
            out += [a, b]
    return out


RESULT = ["_n_words", "_spans", "_items"]


def find_benchmark(docs: DataFrame, benchmark: DataFrame, text: str = "text", item_id: str = "item_id", item_text: str = "text", window: int = 10, block_words: int = 500_000, names: list[str] = RESULT) -> DataFrame:
    """``docs`` with three columns, by default ``_n_words``, ``_spans`` (flat, disjoint [start, end) word positions) and
    ``_items`` (ids as sorted strings)."""
    sc = docs.sparkSession.sparkContext
    found = docs.drop(*names)
    schema = ", ".join([*(f"`{f.name}` {f.dataType.simpleString()}" for f in found.schema.fields), f"`{names[0]}` bigint, `{names[1]}` array<int>, `{names[2]}` array<string>"])
    last = None
    for block in itertools.chain(_blocks(benchmark, item_id, item_text, block_words), [None]):
        if block is None and last is not None:
            break
        if last is not None:
            found = stored(found, "op2-found")
            last.unpersist()
        searched = last is not None
        last = sc.broadcast((block or [], window))
        found = found.mapInArrow(_pass(last, text, names, not searched), schema)
    return found


def hit_words(spans):
    return F.aggregate(F.transform(spans, lambda x, i: F.when(i % 2 == 0, -x).otherwise(x)), F.lit(0).cast("bigint"), lambda a, x: a + x)


def remove_contaminated(docs: DataFrame, benchmark: DataFrame) -> DataFrame:
    """``docs`` without those in which a benchmark window occurs; columns as they were."""
    names = free_names(docs, *RESULT)
    found = find_benchmark(docs, benchmark, names=names)
    return found.where(F.size(names[2]) + F.size(names[1]) == 0).select(*(F.col(f"`{c}`") for c in docs.columns))


def op2_wu_manber_decontamination(spark, sf_dir: str) -> DataFrame:
    bounded_batches(spark)
    docs = spark.read.parquet(f"{sf_dir}/documents.parquet").select("doc_id", "text")
    found = find_benchmark(docs, spark.read.parquet(f"{sf_dir}/benchmark.parquet"))
    n_hit = hit_words(F.col("_spans"))
    return found.select(
        "doc_id",
        F.col("_n_words").alias("n_words"),
        n_hit.alias("n_hit"),
        F.size("_items").cast("bigint").alias("n_items"),
        F.sha2(F.array_join("_items", ","), 256).alias("items_sha256"),
        (n_hit > 0).alias("contaminated"),
    )


SQL = r"""
WITH d AS (SELECT doc_id, row_number() OVER () AS r, regexp_extract_all(translate(coalesce(text, ''), 'ABCDEFGHIJKLMNOPQRSTUVWXYZ', 'abcdefghijklmnopqrstuvwxyz'), '[^\x00-\x2F\x3A-\x60\x7B-\x7F]+') AS w FROM documents),
b AS (SELECT item_id, regexp_extract_all(translate(coalesce(text, ''), 'ABCDEFGHIJKLMNOPQRSTUVWXYZ', 'abcdefghijklmnopqrstuvwxyz'), '[^\x00-\x2F\x3A-\x60\x7B-\x7F]+') AS w FROM benchmark),
p AS (SELECT DISTINCT item_id, least(10, len(w)) AS n, array_to_string(w[i:i + least(10, len(w)) - 1], ' ') AS g FROM (SELECT item_id, w, unnest(range(1, greatest(len(w) - 10, 0) + 2)) AS i FROM b WHERE len(w) > 0)),
sizes AS (SELECT DISTINCT n FROM p),
g AS (SELECT r, i, n, array_to_string(w[i:i + n - 1], ' ') AS g FROM (SELECT r, w, n, unnest(range(1, len(w) - n + 2)) AS i FROM d, sizes WHERE len(w) >= n)),
hit AS (SELECT g.r, g.i, g.n, p.item_id FROM g JOIN p ON g.g = p.g AND g.n = p.n),
words AS (SELECT r, count(DISTINCT x) AS n_hit FROM (SELECT r, unnest(range(i, i + n)) AS x FROM hit) GROUP BY r),
items AS (SELECT r, count(DISTINCT item_id) AS n_items, string_agg(item_id::VARCHAR, ',' ORDER BY item_id::VARCHAR) AS s FROM (SELECT DISTINCT r, item_id FROM hit) GROUP BY r)
SELECT doc_id, len(w)::BIGINT AS n_words, coalesce(n_hit, 0)::BIGINT AS n_hit, coalesce(n_items, 0)::BIGINT AS n_items, sha256(coalesce(s, '')) AS items_sha256, coalesce(n_hit, 0) > 0 AS contaminated
FROM d LEFT JOIN words USING (r) LEFT JOIN items USING (r)
"""
