"""Sweeps counted tile by tile against all pairs written out."""

import random
from itertools import combinations

import numpy as np
import pytest
from pyspark.sql import functions as F

from figmine.operators import dedup, fingerprints, sweeps
from figmine.plans import chain_queries, scan_queries


def _texts():
    rng = random.Random(5)
    words = [f"w{k}" for k in range(300)]
    texts = [None, "", "  ", "One", "one ", "one two", "a a a a a", "a a a a a a a"]
    for _ in range(12):
        base = [rng.choice(words) for _ in range(40)]
        texts += [" ".join(base)] * 2 + [" ".join(base).upper()]
        for swaps in (1, 2, 3, 4, 5, 8):
            near = list(base)
            for k in rng.sample(range(40), swaps):
                near[k] = rng.choice(words)
            texts.append(" ".join(near[: rng.choice((30, 40))]))
    return texts


def _sets(texts):
    out = []
    for t in texts:
        w = (t or "").lower().split()
        out.append({" ".join(w[k : k + 3]) for k in range(max(1, len(w) - 2))} if w else set())
    return out


def _true(texts):
    s = _sets(texts)
    return {(i, j) for i, j in combinations(range(len(texts)), 2) if s[i] and 2 * len(s[i] & s[j]) >= len(s[i] | s[j])}


@pytest.fixture(scope="module")
def docs(spark, tmp_path_factory):
    d = str(tmp_path_factory.mktemp("sweeps"))
    spark.createDataFrame(list(enumerate(_texts())), "doc_id long, text string").write.parquet(f"{d}/documents.parquet")
    return d


def test_true_pairs(spark, monkeypatch):
    texts = _texts()
    monkeypatch.setattr(sweeps, "BLOCK", 16)  # many blocks, and sides longer than one
    rows = spark.createDataFrame(list(enumerate(texts)), "id long, text string")
    named = {r["id"]: r["class"] for r in sweeps.with_class(rows).collect()}
    found = [(r["a"], r["b"]) for r in sweeps.true_pairs(rows).collect()]
    assert len(found) == len({frozenset(p) for p in found})
    met = {frozenset(p) for p in found}
    assert {(i, j) for i, j in combinations(named, 2) if named[i] and (named[i] == named[j] or frozenset((named[i], named[j])) in met)} == _true(texts)


def _best(pairs, truth, ascending):
    best = None
    for cut in sorted({s for s, _ in pairs}, reverse=not ascending):
        inside = [t for s, t in pairs if (s <= cut if ascending else s >= cut)]
        p, r = sum(inside) / len(inside), sum(inside) / truth
        f1 = round(2 * p * r / (p + r), 6) if p + r else None
        if f1 is not None and (best is None or f1 > best[-1]):
            best = (cut, len(inside), sum(inside), f1)
    return best


def _same(got, wanted):
    assert {k: v[1:3] for k, v in got.items()} == {k: v[1:3] for k, v in wanted.items()}
    for k, v in wanted.items():
        assert got[k][0] == pytest.approx(v[0]) and got[k][3] == pytest.approx(v[3], abs=2e-6)


def _rows(df):
    return {r[0]: (r["threshold"], r["found"], r["both"], r["f1"]) for r in df.collect()}


@pytest.mark.parametrize(("whole", "tile"), [(None, None), (0, 20)])
def test_sweeps_equal_all_pairs(spark, docs, monkeypatch, whole, tile):
    """Also with a cut in every tile, and with rows and columns in several steps."""
    if tile:
        for name, value in (("WHOLE", whole), ("TILE", tile), ("ROWS", 8), ("COLUMNS", 16), ("SHARE", 0.05), ("STEP", 64)):
            monkeypatch.setattr(sweeps, name, value)
    texts = _texts()
    true = _true(texts)
    hashes = {"sign64": (fingerprints.sign_hash, {"bits": 64}), "sign144": (fingerprints.sign_hash, {"bits": 144}), "sign256": (fingerprints.sign_hash, {"bits": 256})} | {f"dct{k}": (fingerprints.dct_hash, {"side": k}) for k in (8, 12, 16, 24)}
    rows = spark.createDataFrame(list(enumerate(texts)), "id long, text string")
    wanted = {}
    for name, (f, options) in hashes.items():
        h = {r["id"]: int(r["hash"], 16) for r in f(rows, **options).collect() if r["hash"]}
        wanted[name] = _best([((h[i] ^ h[j]).bit_count(), (i, j) in true) for i, j in combinations(sorted(h), 2)], len(true), True)
    _same(_rows(chain_queries.sweep_hashes(spark, docs)), wanted)
    wanted = {}
    for name, (kind, n, width) in fingerprints.ENCODERS.items():
        v = {i: x for i, t in enumerate(texts) if (x := fingerprints.encode(t, kind, n, width)) is not None}
        wanted[name] = _best([(round(float(v[i] @ v[j]), 4), (i, j) in true) for i, j in combinations(sorted(v), 2)], len(true), False)
    _same(_rows(chain_queries.sweep_vectors(spark, docs)), wanted)
    fitted = scan_queries.fitted_hashes(rows, ("resize", "pad", "stack")).collect()
    wanted = {}
    for fit in ("resize", "pad", "stack"):
        h = {r["id"]: int.from_bytes(r[fit], "big") for r in fitted}
        wanted[fit] = _best([((h[i] ^ h[j]).bit_count(), (i, j) in true) for i, j in combinations(sorted(h), 2)], len(true), True)
    _same(_rows(scan_queries.w06_fit_ablation(spark, docs)), wanted)


def test_a_cut_that_hides_the_best_is_taken_back(spark):
    """True pairs that are far apart: the counted part says nothing of them, so all is counted."""
    bits = [bytes(18), bytes([1] + [0] * 17), bytes([2] + [0] * 17), b"\xff" * 9 + bytes(9), b"\xff" * 4 + bytes(14)]
    rows = spark.createDataFrame([(k + 1, bytearray(b)) for k, b in enumerate(bits)], "class long, h binary")
    pairs = spark.createDataFrame([(1, 4)], "a long, b long")
    cut, all_ = (_rows(sweeps.best_of(rows, pairs, {"h": sweeps.bits(144)}, ["h"], "hash", whole=w)) for w in (0, None))
    assert cut == all_ and all_["h"][2] == 1


def test_counts_are_those_of_the_encoders():
    seen = {}
    for text in (*_texts(), "é" * 9 + "ab", "x"):
        for kind, n, width in fingerprints.ENCODERS.values():
            one, other = fingerprints.counts(text, kind, n, width, seen), fingerprints.encode(text, kind, n, width)
            assert (one is None) == (other is None)
            assert one is None or np.allclose(one / np.sqrt(one.astype(float) @ one), other)


def test_no_pairs_are_written(spark, docs):
    """What the tiles return is counts: far fewer rows than pairs."""
    rows = spark.createDataFrame([(0, bytearray(k.to_bytes(8, "big"))) for k in range(3000)], "class long, h binary")
    none = spark.createDataFrame([], "a long, b long")
    counts = sweeps.score_counts(rows, none, {"h": sweeps.bits(64)})
    assert counts.count() < 1000 and counts.agg(F.sum("n")).first()[0] == 3000 * 2999 // 2
    assert dedup.sweep_counts(spark.createDataFrame([(1, 2, 1)], "score int, n bigint, t bigint"), 1, True).first()["found"] == 2
