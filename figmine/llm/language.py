"""Language identification by word-first backoff.

A known word adds its log frequency in each language. A word that training did not see falls back to its character
n-grams, longest first: the first length at which any n-gram is known decides, down to single characters.

The tables are learned from about ``TRAIN_ROWS`` labelled rows at most, picked by a hash of the id in each language so
that a rare language keeps its rows, and hold every gram counted there more than once (single characters always);
scoring covers every word of every text.

Nulls and edge cases: a null text, or one without a letter, is ``und`` with score 0, and so is every text when
nothing was learned; rows with a null language or id teach nothing; a null id is still predicted, as not held out;
repeated rows are scored each; equal scores go to the alphabetically first language; extra columns are ignored.
"""

from __future__ import annotations

import numpy as np
import pyarrow as pa
import pyarrow.compute as pc
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from . import textvec as V
from .common import bounded_batches, free_names, remainder

TRAIN_ROWS = 20_000
LONGEST = 5


def _grams(step: V.Step, start: np.ndarray, end: np.ndarray, n: int):
    """Hashes of the n-character grams of the given words, and the word each belongs to."""
    heads = np.flatnonzero((step.data & 0xC0) != 0x80)
    a, b = np.searchsorted(heads, start), np.searchsorted(heads, end)
    count = np.maximum(b - a - n + 1, 0)
    word = np.repeat(np.arange(len(start)), count)
    at = np.repeat(a, count) + np.arange(count.sum()) - np.repeat(np.cumsum(count) - count, count)
    tail = np.append(heads, len(step.data))
    return V.mix(step.span_hash(heads[at], tail[at + n]) + np.uint64(n)), word


def _count(batches):
    """(lang, gram length or 0 for a word, hash, count) of labelled texts."""
    for batch in batches:
        langs = np.array(batch.column(1).to_pylist(), object)
        for first, step in V.steps(batch.column(0)):
            start, end, bounds = step.words(V.NON_WORD)
            of_text = np.repeat(np.arange(len(bounds) - 1), np.diff(bounds))
            lang_of_word = langs[first : first + len(bounds) - 1][of_text] if len(of_text) else np.zeros(0, object)
            for lang in sorted(set(lang_of_word.tolist())):
                own = np.flatnonzero(lang_of_word == lang)
                out = []
                h, c = np.unique(step.span_hash(start[own], end[own]), return_counts=True)
                out.append((0, h, c))
                for n in range(1, LONGEST + 1):
                    h, c = np.unique(_grams(step, start[own], end[own], n)[0], return_counts=True)
                    out.append((n, h, c))
                size = sum(len(x[1]) for x in out)
                yield pa.RecordBatch.from_arrays(
                    [pa.array([lang] * size, pa.string()), pa.array(np.concatenate([np.full(len(x[1]), x[0], np.int32) for x in out])), pa.array(np.concatenate([x[1] for x in out]).view(np.int64)), pa.array(np.concatenate([x[2] for x in out]).astype(np.int64))],
                    names=["lang", "n", "gram", "count"],
                )


class LanguageModel:
    """Per gram length (0: words) a sorted hash table and log frequencies by language."""

    def __init__(self, langs: list[str], rows: pa.Table):
        """``rows``: place of the language, gram length, hash and count."""
        self.langs = langs
        place, length, gram, count = (rows.column(k).to_numpy() for k in range(4))
        self.tables = {}
        for n in range(LONGEST + 1):
            own = length == n
            keys, inverse = np.unique(gram[own].astype(np.int64).view(np.uint64), return_inverse=True)
            counts = np.zeros((len(keys), len(langs)))
            np.add.at(counts, (inverse, place[own]), count[own])
            logs = np.log((counts + 0.2) / (counts.sum(axis=0) + 0.2 * max(len(keys), 1))) if len(keys) else counts
            self.tables[n] = (keys, logs)

    def score(self, step: V.Step) -> tuple[np.ndarray, np.ndarray]:
        """Log scores by text and language, and words per text."""
        start, end, bounds = step.words(V.NON_WORD)
        hashes, where, inverse = np.unique(step.span_hash(start, end), return_index=True, return_inverse=True)
        start, end = start[where], end[where]
        keys, logs = self.tables[0]
        at = V.position_of(keys, hashes)
        value = np.zeros((len(hashes), len(self.langs)))
        value[at >= 0] = logs[at[at >= 0]]
        open_ = np.flatnonzero(at < 0)
        for n in range(LONGEST, 0, -1):
            keys, logs = self.tables[n]
            if not len(open_) or not len(keys):
                continue
            grams, word = _grams(step, start[open_], end[open_], n)
            at = V.position_of(keys, grams)
            word, at = word[at >= 0], at[at >= 0]
            known = np.bincount(word, minlength=len(open_))
            for k in range(len(self.langs)):
                value[open_, k] += np.bincount(word, weights=logs[at, k], minlength=len(open_)) / np.maximum(known, 1)
            open_ = open_[known == 0]
        return V.per_text_sum(value[inverse], bounds), np.diff(bounds)


def shares(counts: dict[str, int], bound: int) -> dict[str, int]:
    """Rows to take of each language, ``bound`` in all at most: small ones whole, the rest in equal parts."""
    out, left = {}, bound
    for k, (lang, n) in enumerate(sorted(counts.items(), key=lambda x: (x[1], x[0]))):
        out[lang] = min(n, max(1, left // (len(counts) - k)))
        left -= out[lang]
    return out


def sampled_by(rows: DataFrame, doc_id: str, lang: str, bound: int) -> DataFrame:
    """About ``bound`` of the rows at most, picked by a hash of the id within each language."""
    counts = {r[0]: r[1] for r in rows.groupBy(lang).agg(F.count("*")).collect()}
    if sum(counts.values()) <= bound:
        return rows
    cuts = F.create_map(*[F.lit(x) for k, n in shares(counts, bound).items() for x in (k, -(-(n << 20) // counts[k]))])
    return rows.where(F.pmod(F.xxhash64(F.col(doc_id).cast("string"), F.lit("sample")), F.lit(1 << 20)) < F.element_at(cuts, F.col(lang)))


def train(docs: DataFrame, doc_id: str = "doc_id", text: str = "text", lang: str = "lang", train_rows: int = TRAIN_ROWS) -> LanguageModel:
    rows = docs.where(F.col(lang).isNotNull() & (remainder(doc_id, 5) != 0))
    counted = sampled_by(rows.select(doc_id, text, lang), doc_id, lang, train_rows).select(text, lang).mapInArrow(_count, "lang string, n int, gram bigint, count bigint")
    table = counted.groupBy("lang", "n", "gram").agg(F.sum("count").alias("count")).where((F.col("count") > 1) | (F.col("n") == 1))
    found = table.select("lang", "n", "gram", "count").toArrow()
    langs = found.column(0).unique().to_pylist()
    names = sorted(langs)
    place = pc.index_in(found.column(0), pa.array(names, pa.string()))
    return LanguageModel(names, found.set_column(0, "lang", place))


def _no_letter(column, first: int, step: V.Step) -> np.ndarray:
    letter = np.zeros(256, bool)
    letter[65:91] = letter[97:123] = True
    seen = np.concatenate([[0], np.cumsum(letter[step.data])])
    none = seen[step.bounds[1:]] == seen[step.bounds[:-1]]
    for k in np.flatnonzero(none):
        none[k] = not any(c.isalpha() for c in (column[first + int(k)].as_py() or ""))
    return none


def predict(docs: DataFrame, model: LanguageModel, text: str = "text", names: tuple[str, str] = ("lang_pred", "score")) -> DataFrame:
    """``docs`` with ``lang_pred`` and ``score``, the posterior of a text of at most 20 words at the same rate. A given
    column of such a name is replaced."""
    docs = docs.drop(*names)
    shared = docs.sparkSession.sparkContext.broadcast(model)

    def run(batches):
        m = shared.value
        for batch in batches:
            column = batch.column(batch.schema.names.index(text))
            lang, score = [], []
            for first, step in V.steps(column):
                if not m.langs:
                    lang += ["und"] * (len(step.bounds) - 1)
                    score += [0.0] * (len(step.bounds) - 1)
                    continue
                logs, words = m.score(step)
                best = logs.argmax(axis=1)
                rate = np.minimum(1, 20 / np.maximum(words, 1))[:, None]
                p = 1 / np.exp((logs - logs.max(axis=1, keepdims=True)) * rate).sum(axis=1)
                none = _no_letter(column, first, step)
                lang += ["und" if x else m.langs[b] for x, b in zip(none, best)]
                score += np.where(none, 0.0, p).tolist()
            yield pa.RecordBatch.from_arrays([*batch.columns, pa.array(lang, pa.string()), pa.array(score, pa.float64())], names=[*batch.schema.names, *names])

    schema = ", ".join([*(f"`{f.name}` {f.dataType.simpleString()}" for f in docs.schema.fields), f"`{names[0]}` string, `{names[1]}` double"])
    return docs.mapInArrow(run, schema)


def keep_identified(docs: DataFrame, least: float = 0.5) -> DataFrame:
    """``docs`` without texts that have no language: no letter, or no language with at least ``least`` of the weight."""
    plain = docs.select(*docs.columns)
    model = train(plain)
    if not model.langs:
        return plain.where(F.col("text").rlike(r"\p{L}"))
    lang, score = free_names(docs, "lang_pred", "score")
    return predict(plain, model, names=(lang, score)).where((F.col(lang) != "und") & (F.col(score) >= least)).select(*(F.col(f"`{c}`") for c in docs.columns))


def op10_word_backoff_language(spark, sf_dir: str) -> DataFrame:
    bounded_batches(spark)
    docs = spark.read.parquet(f"{sf_dir}/documents.parquet")
    model = train(docs)
    held = F.coalesce(remainder("doc_id", 5) == 0, F.lit(False))
    return predict(docs.select("doc_id", "text"), model).select("doc_id", held.alias("held_out"), "lang_pred", "score")
