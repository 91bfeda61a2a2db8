"""Toxicity after noisy-channel deobfuscation.

Channel: a spelling that hides a word (digits and signs for letters, letters spread out, letters repeated) is a
lattice of the characters it may stand for. A character trigram model of the training texts decodes the lattice by
Viterbi, and the restored word takes the place of the spelling; where a spelling can be cut in two ways, the other
reading is scored too. Score: the restored text is scored by the words and
word beginnings that mark toxic training texts, brought to a probability by a logistic fit.

Every labelled row teaches: six in ten count marks and trigrams, the others fit the logistic weights, by sums over all
of them. The lexicon keeps the ``LEXICON`` strongest entries and the character model the ``TRIGRAMS`` commonest, so what
is broadcast has a fixed bound. Every word of every text is scored.

Nulls and edge cases: a null or empty text gets the score of a text without any marked word; rows with a null id or
label teach nothing; a null id is scored, as not held out; repeated rows are scored each; without labels of both kinds
every score is 0; extra columns are ignored.
"""

from __future__ import annotations

import math
import re
from collections import Counter

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from . import textvec as V
from .common import Scratch, bounded_batches, remainder

LEXICON = 20_000
TRIGRAMS = 60_000
#: Distinct keys and words that a worker holds before it passes partial counts on.
COUNTED = 400_000
FEATURES = 6
BEGINNING = 6  # bytes of a word's beginning

#: What a sign may stand for.
STANDS_FOR = {"0": "o", "1": "il", "3": "e", "4": "a", "5": "s", "7": "t", "8": "b", "9": "g", "@": "a", "$": "s", "!": "i", "|": "il", "+": "t", "*": "aeiou"}

_SIGNS = re.escape("".join(STANDS_FOR))
#: What may stand between the letters of a spread word, the same or now this, now that.
_BETWEEN = r"[ .\-_*]"
_HIDDEN = re.compile(
    rf"(?<![\w@$!|+])(?P<spread>[A-Za-z{_SIGNS}](?:{_BETWEEN}[A-Za-z{_SIGNS}]){{2,}})(?![\w@$!|+])"
    rf"|(?<![\w@$!|+*])(?=[{_SIGNS}]*[A-Za-z])(?=[A-Za-z]*[{_SIGNS}])[A-Za-z{_SIGNS}]+(?![\w@$!|+])"
    r"|(?<![\w@$!|+])[^\W\d_]*([A-Za-z])\2{2,}[^\W\d_]*(?![\w@$!|+])"
)
_PROBABLE = re.compile(rf"[{_SIGNS}][A-Za-z]|[A-Za-z][{_SIGNS}]|([A-Za-z])\1\1|(?<!\w)[A-Za-z{_SIGNS}]{_BETWEEN}[A-Za-z{_SIGNS}]{_BETWEEN}[A-Za-z{_SIGNS}](?!\w)")
_LETTERS = re.compile(r"[^\W\d_]+")
#: Signs that also just end a word.
_ENDS = re.compile(r"[!|+*]+$")


def _lattice(spelling: str) -> list[list[str]]:
    """For each place the strings it may stand for."""
    s = spelling.lower()
    out, k = [], 0
    while k < len(s):
        n = 1
        while k + n < len(s) and s[k + n] == s[k]:
            n += 1
        options = list(STANDS_FOR.get(s[k], s[k]))
        out.append([o * c for o in options for c in ((1, 2) if n > 2 else (n,))])
        k += n
    return out


class CharacterModel:
    def __init__(self, trigrams: dict[str, float]):
        self.trigrams = trigrams
        self.contexts: Counter = Counter()
        for t, c in trigrams.items():
            self.contexts[t[:2]] += c
        self.cache: dict[tuple, tuple[float, str]] = {}

    def cost(self, context: str, char: str) -> float:
        return -math.log((self.trigrams.get(context + char, 0) + 0.02) / (self.contexts.get(context, 0) + 1.0))

    def decode(self, spelling: str) -> tuple[float, str]:
        """Cost and word of the cheapest path."""
        if spelling in self.cache:
            return self.cache[spelling]
        best = {"^^": (0.0, "")}
        for options in _lattice(spelling):
            after: dict[str, tuple[float, str]] = {}
            for context, (cost, said) in best.items():
                for option in options:
                    c, ctx = cost, context
                    for char in option:
                        c += self.cost(ctx, char)
                        ctx = ctx[1] + char
                    if ctx not in after or c < after[ctx][0]:
                        after[ctx] = (c, said + option)
            best = after
        word = min((cost + self.cost(context, "^"), said) for context, (cost, said) in best.items())
        if len(self.cache) > 200_000:
            self.cache.clear()
        self.cache[spelling] = word
        return word

    def readings(self, found: str, spread: bool) -> list[str]:
        """What a spelling may say, the likeliest first: with signs at its end as letters or as marks that stay, and
        with letters that stand alone before a spread word as part of it or as words."""
        if spread:
            # letters stand at the even places, what is between them at the odd ones
            letters, between = found[::2], found[1::2]
            said = [self.decode(letters)]
            for k in (1, 2):
                head, rest = letters[:k], letters[k:]
                if len(rest) >= 3 and between[k - 1] == " " and all(c.isalpha() for c in head):
                    parts = [self.decode(c) for c in head] + [self.decode(rest)]
                    said.append((sum(c for c, _ in parts), " ".join([*head, parts[-1][1]])))
            return [word for _, word in sorted(said, key=lambda x: x[0])]
        said = [self.decode(found)]
        if m := _ENDS.search(found):
            stem = found[: m.start()]
            cost, word = self.decode(stem)
            plain = stem.isalpha() and not re.search(r"([A-Za-z])\1\1", stem)
            said.append((cost, (stem if plain else word) + m.group()))
        return [word for _, word in sorted(said, key=lambda x: x[0])]

    def restore(self, text: str, others: set | None = None) -> str:
        """``text`` with the likeliest reading of every spelling; ``others`` takes the other readings."""

        def one(m: re.Match) -> str:
            found, spread = m.group(), m.group("spread") is not None
            size = (len(found) + 1) // 2 if spread else len(found)
            letters = sum(c.isalpha() for c in found)
            if not letters or size < 3 or 3 * letters < size:
                return found
            best, *rest = self.readings(found, spread)
            # a reading that begins like the best one adds no mark: the beginning is scored as it is
            if others is not None:
                others.update(x for x in rest if x[:BEGINNING].lower() != best[:BEGINNING].lower())
            return best

        return _HIDDEN.sub(one, text) if _PROBABLE.search(text) else text


def _features(step: V.Step):
    start, end, bounds = step.words(V.NON_WORD)
    head = np.minimum(start + BEGINNING, end)
    words = step.span_hash(start, end)
    heads = np.where(end - start >= BEGINNING, V.mix(step.span_hash(start, head) + np.uint64(7)), words)
    return words, heads, bounds


class ToxicModel:
    """Lexicon of hashed words and beginnings, character model and logistic weights."""

    def __init__(self, keys: np.ndarray, weights: np.ndarray, characters: dict[str, float], beta: np.ndarray | None = None):
        order = np.argsort(keys)
        self.keys, self.weights, self.characters, self.beta = keys[order], weights[order], characters, beta

    def describe(self, step: V.Step) -> np.ndarray:
        """Per text: 1, log of the summed weight, weight by word, strongest, marked words by word."""
        words, heads, bounds = _features(step)
        value = np.zeros(len(words))
        for h in (words, heads):
            at = V.position_of(self.keys, h)
            value = np.maximum(value, np.where(at >= 0, self.weights[at] if len(self.weights) else 0, 0))
        n = np.maximum(np.diff(bounds), 1)
        total = V.per_text_sum(value, bounds)
        hits = V.per_text_sum((value > 0).astype(float), bounds)
        strongest = np.zeros(len(n))
        if len(value):
            np.maximum.at(strongest, np.repeat(np.arange(len(n)), np.diff(bounds)), value)
        return np.stack([np.ones(len(n)), np.log1p(total), np.minimum(total / n, 5), strongest, np.minimum(hits / n * 10, 5), np.log1p(hits)], axis=1)


def _marks(batches):
    """(key, tri, pos, neg): toxic and other texts that hold a word or beginning (tri null), or how often their words hold
    a character trigram (key null), each word once a text."""
    held: list[list] = [[], []]
    words: list[Counter] = [Counter(), Counter()]
    size = 0

    def flush():
        keys, inverse = np.unique(np.concatenate([*held[1], *held[0]]), return_inverse=True)
        toxic = sum(len(x) for x in held[1])
        pos = np.bincount(inverse[:toxic], minlength=len(keys))
        neg = np.bincount(inverse[toxic:], minlength=len(keys))
        tri: tuple[Counter, Counter] = (Counter(), Counter())
        for label in (0, 1):
            for w, c in words[label].items():
                w = f"^^{w}^"
                for k in range(len(w) - 2):
                    tri[label][w[k : k + 3]] += c
            held[label].clear()
            words[label].clear()
        both = list(tri[0] | tri[1])
        none = len(both)
        # tables of two long counts and a key, in parts that stay small
        table = pa.table(
            {
                "key": pa.concat_arrays([pa.array(keys.view(np.int64)), pa.nulls(none, pa.int64())]),
                "tri": pa.concat_arrays([pa.nulls(len(keys), pa.string()), pa.array(both, pa.string())]),
                "pos": pa.array([*pos.tolist(), *(tri[1][t] for t in both)], pa.int64()),
                "neg": pa.array([*neg.tolist(), *(tri[0][t] for t in both)], pa.int64()),
            }
        )
        yield from table.to_batches(max_chunksize=20_000)

    for batch in batches:
        toxic = np.array(batch.column(1).to_pylist(), np.int64) > 0
        for first, step in V.steps(batch.column(0)):
            hashes, heads, bounds = _features(step)
            for k in range(len(bounds) - 1):
                a, b = bounds[k], bounds[k + 1]
                own = np.unique(np.concatenate([hashes[a:b], heads[a:b]]))
                held[int(toxic[first + k])].append(own)
                size += len(own)
        for text, t in zip(batch.column(0).to_pylist(), toxic):
            if text:
                words[int(t)].update(set(_LETTERS.findall(text.lower())))
        # a key of many texts is held once a text, so this bounds memory from above
        if size >= 8 * COUNTED or sum(map(len, words)) >= COUNTED:
            yield from flush()
            size = 0
    if any(held) or any(words):
        yield from flush()


def _logistic(seen: DataFrame, ridge: float = 0.05) -> np.ndarray:
    """Weights by Newton steps; each sums over all rows of ``seen`` (x, y), of which only the sums reach the driver."""
    beta = np.zeros(FEATURES)

    def sums(at: np.ndarray):
        def run(batches):
            curve, slope = np.zeros((FEATURES, FEATURES)), np.zeros(FEATURES)
            for batch in batches:
                x = np.asarray(batch.column(0).flatten()).reshape(-1, FEATURES)
                p = 1 / (1 + np.exp(-np.clip(x @ at, -30, 30)))
                w = np.maximum(p * (1 - p), 1e-6)
                curve += (x * w[:, None]).T @ x
                slope += x.T @ (np.asarray(batch.column(1)) - p)
            yield pa.RecordBatch.from_arrays([pa.array([curve.ravel().tolist()], pa.list_(pa.float64())), pa.array([slope.tolist()], pa.list_(pa.float64()))], names=["curve", "slope"])

        return run

    for _ in range(50):
        parts = seen.mapInArrow(sums(beta), "curve array<double>, slope array<double>").collect()
        curve = sum(np.array(r["curve"]) for r in parts).reshape(FEATURES, FEATURES)
        slope = sum(np.array(r["slope"]) for r in parts)
        step = np.linalg.solve(curve + ridge * np.eye(FEATURES), slope - ridge * beta)
        beta = beta + step
        if np.abs(step).max() < 1e-8:
            break
    return beta


def train(docs: DataFrame, labels: DataFrame, lexicon: int = LEXICON) -> ToxicModel | None:
    spark = docs.sparkSession
    scratch = Scratch(spark)
    known = labels.where(F.col("toxic").isNotNull() & (remainder("doc_id", 4) != 2)).groupBy("doc_id").agg(F.max(F.col("toxic").cast("int")).alias("toxic"))
    fit = F.pmod(F.xxhash64(F.col("doc_id").cast("string"), F.lit("half")), F.lit(10)) < 6
    # labels grow with the documents: the joins below are merged at every size and broadcast at none
    learn = docs.select("doc_id", "text").where(remainder("doc_id", 4) != 2)
    sizes = {r["toxic"]: r["n"] for r in known.where(fit).groupBy((F.col("toxic") > 0).cast("int").alias("toxic")).agg(F.count("*").alias("n")).collect()}
    p, n = sizes.get(1, 0), sizes.get(0, 0)
    if not p or not n:
        return None
    counted = learn.where(fit).join(known.where(fit).hint("merge"), "doc_id").select("text", "toxic").mapInArrow(_marks, "key bigint, tri string, pos bigint, neg bigint")
    table = scratch.put(counted.groupBy("key", "tri").agg(F.sum("pos").alias("pos"), F.sum("neg").alias("neg")).where("tri IS NOT NULL OR pos >= 4"), "op6-counts")
    odds = F.log(((F.col("pos") + 0.5) / (p + 1)) / ((F.col("neg") + 0.5) / (n + 1)))
    marked = table.where("key IS NOT NULL").withColumn("weight", odds).where(F.col("weight") > 1.2)
    marked = marked.withColumn("gain", F.col("pos") * F.col("weight")).where("gain > 14").orderBy(F.desc("gain"), "key").limit(lexicon).collect()
    # both kinds of text weigh the same in the character model
    share = F.col("pos") / F.lit(float(p)) + F.col("neg") / F.lit(float(n))
    characters = table.where("tri IS NOT NULL").select("tri", (share * F.lit(1000.0)).alias("w")).orderBy(F.desc("w"), "tri").limit(TRIGRAMS).collect()
    scratch.drop(table)
    model = ToxicModel(np.array([r["key"] for r in marked], np.int64).astype(np.uint64), np.array([r["weight"] for r in marked], float), {r["tri"]: r["w"] for r in characters})
    shared = spark.sparkContext.broadcast(model)

    def describe(batches):
        m = shared.value
        for batch in batches:
            x = np.concatenate([m.describe(s) for _, s in V.steps(batch.column(1))] or [np.zeros((0, FEATURES))])
            yield pa.RecordBatch.from_arrays([batch.column(0), pa.array(x.tolist(), pa.list_(pa.float64()))], names=["doc_id", "x"])

    def seen(which) -> DataFrame:
        # texts are described where they lie: only their few numbers move to meet the labels
        described = learn.where(which).mapInArrow(describe, f"doc_id {learn.schema['doc_id'].dataType.simpleString()}, x array<double>")
        return scratch.put(described.join(known.where(which).hint("merge"), "doc_id").select("x", (F.col("toxic") > 0).cast("double").alias("y")), "op6-described")

    found = seen(~fit)
    if found.agg(F.count_distinct("y")).first()[0] < 2:
        scratch.drop(found)
        found = seen(F.lit(True))
    model.beta = _logistic(found)
    scratch.drop(found)
    return model


def score(docs: DataFrame, model: ToxicModel | None, text: str = "text") -> DataFrame:
    """``docs`` with ``restored`` (whether a spelling was decoded) and ``score``; given columns of such names are replaced."""
    docs = docs.drop("restored", "score")
    shared = docs.sparkSession.sparkContext.broadcast(model)

    def run(batches):
        m = shared.value
        characters = CharacterModel(m.characters) if m else None
        for batch in batches:
            column = batch.column(batch.schema.names.index(text))
            scores = np.zeros(len(column))
            changed = np.zeros(len(column), bool)
            if m:
                for at in range(0, len(column), 256):
                    raw = column.slice(at, 256).to_pylist()
                    others = [set() for _ in raw]
                    restored = [characters.restore(t, o) if t else t for t, o in zip(raw, others)]
                    changed[at : at + len(raw)] = [a is not b and a != b for a, b in zip(raw, restored)]
                    restored = [" ".join([t, *sorted(o)]) if o else t for t, o in zip(restored, others)]
                    for first, step in V.steps(pa.array(restored, pa.string())):
                        x = m.describe(step)
                        scores[at + first : at + first + len(x)] = 1 / (1 + np.exp(-np.clip(x @ m.beta, -30, 30)))
            yield pa.RecordBatch.from_arrays([*batch.columns, pa.array(changed), pa.array(scores)], names=[*batch.schema.names, "restored", "score"])

    schema = ", ".join([*(f"`{f.name}` {f.dataType.simpleString()}" for f in docs.schema.fields), "restored boolean, score double"])
    return docs.mapInArrow(run, schema)


def op6_noisy_channel_toxicity(spark, sf_dir: str) -> DataFrame:
    bounded_batches(spark)
    docs = spark.read.parquet(f"{sf_dir}/documents.parquet").select("doc_id", "text")
    model = train(docs, spark.read.parquet(f"{sf_dir}/labels.parquet"))
    held = F.coalesce(remainder("doc_id", 4) == 2, F.lit(False))
    return score(docs, model).select("doc_id", held.alias("held_out"), "score", (F.col("score") >= 0.3).cast("int").alias("predicted"), "restored")
