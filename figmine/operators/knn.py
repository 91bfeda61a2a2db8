"""Nearest neighbours: exact, a layered proximity graph per shard, inverted cells, and random hyperplanes."""

from __future__ import annotations

import heapq

import numpy as np
import pandas as pd
from pyspark.sql import DataFrame, Window
from pyspark.sql import functions as F


class LayeredGraph:
    """A navigable small-world graph with layers over unit vectors, by inner product."""

    def __init__(self, links: int = 12, build_list: int = 100, seed: int = 1):
        self.links, self.build_list = links, build_list
        self.rng = np.random.default_rng(seed)
        self.vectors = np.zeros((0, 0), np.float32)
        self.size = 0
        self.layers: list[dict[int, np.ndarray]] = []
        self.entry = -1

    def _search(self, q: np.ndarray, starts: list[int], width: int, layer: dict[int, np.ndarray]) -> list[tuple[float, int]]:
        seen = set(starts)
        sims = self.vectors[starts] @ q
        todo = [(-float(s), k) for s, k in zip(sims, starts)]
        best = [(float(s), k) for s, k in zip(sims, starts)]
        heapq.heapify(todo)
        heapq.heapify(best)
        while len(best) > width:
            heapq.heappop(best)
        while todo:
            far, k = heapq.heappop(todo)
            if -far < best[0][0] and len(best) >= width:
                break
            fresh = [int(x) for x in layer.get(k, ()) if int(x) not in seen]
            if not fresh:
                continue
            seen.update(fresh)
            for s, x in zip((self.vectors[fresh] @ q).tolist(), fresh):
                if len(best) < width or s > best[0][0]:
                    heapq.heappush(todo, (-s, x))
                    heapq.heappush(best, (s, x))
                    if len(best) > width:
                        heapq.heappop(best)
        return sorted(best, reverse=True)

    def add_batch(self, batch: np.ndarray) -> None:
        first = self.size
        batch = batch.astype(np.float32)
        self.vectors = batch if not first else np.concatenate([self.vectors, batch])
        heights = np.minimum((-np.log(np.maximum(self.rng.random(len(batch)), 1e-12)) / np.log(self.links)).astype(int), 12)
        for k, h in enumerate(heights.tolist(), first):
            self._insert(k, h)
            self.size += 1

    def _insert(self, k: int, height: int) -> None:
        q = self.vectors[k]
        starts = [self.entry] if self.entry >= 0 else []
        for level in range(len(self.layers) - 1, height, -1):
            if starts:
                starts = [self._search(q, starts, 1, self.layers[level])[0][1]]
        for level in range(min(height, len(self.layers) - 1), -1, -1):
            near = self._search(q, starts, self.build_list, self.layers[level])
            own = [x for _, x in near[: self.links]]
            self.layers[level][k] = np.array(own, np.int64)
            most = self.links * (2 if level == 0 else 1)
            for x in own:
                back = np.append(self.layers[level][x], k)
                if len(back) > most:
                    back = back[np.argsort(-(self.vectors[back] @ self.vectors[x]))[:most]]
                self.layers[level][x] = back
            starts = [x for _, x in near]
        while len(self.layers) <= height:
            self.layers.append({k: np.zeros(0, np.int64)})
            self.entry = k

    def query(self, q: np.ndarray, k: int, search_list: int = 30) -> list[tuple[float, int]]:
        if self.entry < 0:
            return []
        starts = [self.entry]
        for level in range(len(self.layers) - 1, 0, -1):
            starts = [self._search(q, starts, 1, self.layers[level])[0][1]]
        return self._search(q, starts, max(k, search_list), self.layers[0])[:k]

    def to_bytes(self) -> bytes:
        import pickle

        return pickle.dumps((self.links, self.build_list, self.vectors, self.layers, self.entry))

    @staticmethod
    def from_bytes(raw: bytes) -> LayeredGraph:
        import pickle

        g = LayeredGraph()
        g.links, g.build_list, g.vectors, g.layers, g.entry = pickle.loads(raw)
        g.size = len(g.vectors)
        return g


def _merge(found: DataFrame, k: int) -> DataFrame:
    order = Window.partitionBy("id").orderBy(F.desc("similarity"), "neighbour")
    return found.withColumn("rank", F.row_number().over(order)).where(F.col("rank") <= k).select("id", "rank", "neighbour", "similarity")


def _tiles(vectors: DataFrame, shards: int):
    rows = vectors.where("vec IS NOT NULL").select("id", "vec")
    left = rows.withColumn("shard", F.explode(F.sequence(F.lit(0), F.lit(shards - 1))))
    right = rows.withColumn("shard", F.pmod(F.xxhash64("id"), F.lit(shards)).cast("int"))
    return left, right


def _search_shards(vectors: DataFrame, shards: int, search) -> DataFrame:
    kind = vectors.schema["id"].dataType.simpleString()
    left, right = _tiles(vectors, shards)

    def run(q: pd.DataFrame, c: pd.DataFrame) -> pd.DataFrame:
        if not len(q) or not len(c):
            return pd.DataFrame({"id": [], "neighbour": [], "similarity": []})
        return search(q["id"].to_numpy(), np.stack(q["vec"].to_numpy()), c["id"].to_numpy(), np.stack(c["vec"].to_numpy()))

    return left.groupBy("shard").cogroup(right.groupBy("shard")).applyInPandas(run, f"id {kind}, neighbour {kind}, similarity double")


#: Similarities that a worker holds at once.
HELD = 1 << 23


def _best(q_ids, q, c_ids, c, k: int) -> pd.DataFrame:
    """The ``k`` most similar of ``c`` to each of ``q`` but itself, ties to the earlier row; a bounded block of queries at a time."""
    places: dict = {}
    for at, one in enumerate(c_ids.tolist()):
        places.setdefault(one, []).append(at)
    step = max(1, HELD // max(len(c), 1))
    out = []
    for lo in range(0, len(q), step):
        sims = q[lo : lo + step] @ c.T
        for s, one in zip(sims, q_ids[lo : lo + step].tolist()):
            s[places.get(one, [])] = -np.inf
            near = np.flatnonzero(s >= np.partition(s, len(s) - k)[len(s) - k]) if k < len(s) else np.arange(len(s))
            out += [(one, c_ids[t], float(s[t])) for t in near[np.argsort(-s[near], kind="stable")[:k]] if np.isfinite(s[t])]
    return pd.DataFrame(out, columns=["id", "neighbour", "similarity"])


def knn_exact(vectors: DataFrame, k: int = 30, shards: int = 8) -> DataFrame:
    """(id, rank, neighbour, similarity) among all others, by matrix products tile by tile."""

    def search(q_ids, q, c_ids, c):
        return _best(q_ids, q, c_ids, c, k)

    return _merge(_search_shards(vectors, shards, search), k)


def knn_graph(vectors: DataFrame, k: int = 30, shards: int = 4, links: int = 12, build_list: int = 100, search_list: int = 30) -> DataFrame:
    """The same from one layered graph per shard; every shard answers every query and the answers are merged."""

    def search(q_ids, q, c_ids, c):
        g = LayeredGraph(links, build_list)
        for at in range(0, len(c), 100_000):
            g.add_batch(c[at : at + 100_000])
        out = []
        for r in range(len(q)):
            out += [(q_ids[r], c_ids[x], s) for s, x in g.query(q[r].astype(np.float32), k + 1, search_list) if c_ids[x] != q_ids[r]]
        return pd.DataFrame(out, columns=["id", "neighbour", "similarity"])

    return _merge(_search_shards(vectors, shards, search), k)


def knn_cells(vectors: DataFrame, k: int = 30, cells: int = 16, probes: int = 4, sample: int = 5000, seed: int = 1) -> DataFrame:
    """Inverted cells: centroids from a bounded sample, every row in its nearest cell, each query in ``probes`` cells."""
    rows = vectors.where("vec IS NOT NULL").select("id", "vec")
    picked = rows.orderBy(F.md5(F.col("id").cast("string"))).limit(sample).select("vec").toPandas()
    data = np.stack(picked["vec"].to_numpy())
    centre = data[np.random.default_rng(seed).permutation(len(data))[:cells]]
    for _ in range(10):
        own = (data @ centre.T).argmax(axis=1)
        centre = np.stack([data[own == c].mean(axis=0) if (own == c).any() else centre[c] for c in range(len(centre))])
        centre /= np.maximum(np.linalg.norm(centre, axis=1, keepdims=True), 1e-12)
    shared = rows.sparkSession.sparkContext.broadcast(centre)
    kind = vectors.schema["id"].dataType.simpleString()

    def nearest(n):
        def run(frames):
            for f in frames:
                if len(f):
                    sims = np.stack(f["vec"].to_numpy()) @ shared.value.T
                    f = f.assign(cell=list(np.argsort(-sims, axis=1)[:, :n].astype(np.int32)))
                    yield f[["id", "vec", "cell"]]

        return rows.mapInPandas(run, f"id {kind}, vec array<double>, cell array<int>").withColumn("cell", F.explode("cell"))

    def meet(q: pd.DataFrame, c: pd.DataFrame) -> pd.DataFrame:
        if not len(q) or not len(c):
            return pd.DataFrame({"id": [], "neighbour": [], "similarity": []})
        return _best(q["id"].to_numpy(), np.stack(q["vec"].to_numpy()), c["id"].to_numpy(), np.stack(c["vec"].to_numpy()), k)

    found = nearest(probes).groupBy("cell").cogroup(nearest(1).groupBy("cell")).applyInPandas(meet, f"id {kind}, neighbour {kind}, similarity double")
    return _merge(found, k)


def knn_hyperplanes(vectors: DataFrame, k: int = 30, tables: int = 8, planes: int = 6, seed: int = 1) -> DataFrame:
    """Random hyperplanes: vectors meet where all signs of one table agree."""
    rows = vectors.where("vec IS NOT NULL").select("id", "vec")
    width = rows.select(F.size("vec").alias("n")).first()
    normals = np.random.default_rng(seed).normal(size=(tables * planes, width["n"] if width else 1))
    kind = vectors.schema["id"].dataType.simpleString()

    def sign(frames):
        for f in frames:
            if len(f):
                bits = (np.stack(f["vec"].to_numpy()) @ normals.T > 0).reshape(len(f), tables, planes)
                yield f.assign(keys=list((bits * (1 << np.arange(planes))).sum(axis=2) + (np.arange(tables) << planes)))[["id", "vec", "keys"]]

    keyed = rows.mapInPandas(sign, f"id {kind}, vec array<double>, keys array<long>").withColumn("key", F.explode("keys")).select("id", "vec", "key")

    def meet(f: pd.DataFrame) -> pd.DataFrame:
        v, ids = np.stack(f["vec"].to_numpy()), f["id"].to_numpy()
        out = []
        for at in range(0, len(v), 1024):
            sims = v[at : at + 1024] @ v.T
            for r in range(len(sims)):
                sims[r, at + r] = -np.inf
                out += [(ids[at + r], ids[t], float(sims[r, t])) for t in np.argsort(-sims[r])[:k] if np.isfinite(sims[r, t])]
        return pd.DataFrame(out, columns=["id", "neighbour", "similarity"])

    found = keyed.groupBy("key").applyInPandas(meet, f"id {kind}, neighbour {kind}, similarity double").dropDuplicates(["id", "neighbour"])
    return _merge(found, k)


def edges(neighbours: DataFrame, least: float = 0.86, mode: str = "canonical") -> DataFrame:
    """(src, dst): undirected edges at or above ``least``. ``query_order`` keeps only id < neighbour as found."""
    near = neighbours.where(F.col("similarity") >= least)
    if mode == "query_order":
        return near.where("id < neighbour").select(F.col("id").alias("src"), F.col("neighbour").alias("dst"))
    return near.select(F.least("id", "neighbour").alias("src"), F.greatest("id", "neighbour").alias("dst")).distinct()


def recall(found: DataFrame, truth: DataFrame) -> DataFrame:
    """One row: share of the true (id, neighbour) pairs that were found."""
    hit = truth.select("id", "neighbour").join(found.select("id", "neighbour").withColumn("hit", F.lit(1)), ["id", "neighbour"], "left")
    return hit.agg(F.count("*").alias("truth"), F.count("hit").alias("found"), F.round(F.count("hit") / F.count("*"), 6).alias("recall"))


def search(vectors: DataFrame, probe: list[float], k: int = 10) -> DataFrame:
    """The k nearest of one probe."""
    q = F.array(*[F.lit(float(x)) for x in probe])
    from ..functions.expressions import cosine

    return vectors.where("vec IS NOT NULL").select("id", cosine(F.col("vec"), q).alias("similarity")).orderBy(F.desc("similarity"), "id").limit(k)
