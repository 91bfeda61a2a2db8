"""Exact top-k by exhaustive term-at-a-time accumulation.

A row is a sparse vector: term t is its t-th component, with the integer weight floor(scale * x). The candidates of a
tile are inverted into postings, one list of (row, weight) per term. A query takes its non-zero terms one after the
other and scatters weight * posting into a dense array of scores, one per candidate; a partition select keeps the k
best of the tile, and a window merges the tiles. Every query meets every candidate: the queries are cut into blocks
and the candidates into tiles of bounded size, and a (block, tile) pair is one task's work.

Nulls and edge cases: a row takes no part if its id or vector is null, or a component is null or not finite; an empty
vector scores 0 with all; vectors of different lengths meet on their common terms; ties go to the smaller id; a query
meets every row but those with its own id; repeated rows are candidates each, and a repeated query row gets one answer
list per row; extra columns are ignored; an empty table gives an empty result.
"""

from __future__ import annotations

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame, Window
from pyspark.sql import functions as F

QUERY_BLOCK = 4096
TILE_ROWS = 16384


def _weights(table, scale: int) -> np.ndarray:
    """Rows by terms, floor(scale * x); 0 where a vector is shorter."""
    column = table.column("vector").combine_chunks()
    column = column.chunk(0) if isinstance(column, pa.ChunkedArray) else column
    lengths = np.asarray(pa.compute.list_value_length(column), np.int64)
    flat = np.asarray(column.flatten(), np.float64)
    out = np.zeros((len(lengths), int(lengths.max()) if len(lengths) else 0))
    at = np.arange(out.shape[1])[None, :] < lengths[:, None]
    out[at] = np.floor(scale * flat)
    return out


def _score_tile(scale: int, k: int):
    def run(key, left, right):
        import pyarrow.compute  # noqa: F401

        q, c = _weights(left, scale), _weights(right, scale)
        terms = min(q.shape[1], c.shape[1])
        c_ids = right.column("vec_id").to_numpy()
        order = np.argsort(c_ids, kind="stable")
        c, c_ids = c[order], c_ids[order]
        reach = np.abs(q[:, :terms]).max(initial=0) * np.abs(c[:, :terms]).max(initial=0) * max(terms, 1)
        kind = np.int32 if reach < 2**31 else np.int64 if reach < 2**62 else object
        postings = []
        for t in range(terms):
            rows = np.flatnonzero(c[:, t])
            weight = c[rows, t].astype(kind) if kind is not object else np.array([int(x) for x in c[rows, t]], object)
            postings.append((slice(None) if len(rows) == len(c) else rows, weight))
        uids, q_ids, out = left.column("uid").to_numpy(), left.column("vec_id").to_numpy(), ([], [], [], [])
        for row in range(len(q)):
            scores = np.zeros(len(c), kind)
            for t in np.flatnonzero(q[row, :terms]).tolist():
                rows, weight = postings[t]
                scores[rows] += weight * (int(q[row, t]) if kind is object else kind(q[row, t]))
            lo, hi = np.searchsorted(c_ids, q_ids[row], "left"), np.searchsorted(c_ids, q_ids[row], "right")
            allowed = np.ones(len(c), bool)
            allowed[lo:hi] = False
            places = np.flatnonzero(allowed)
            own = scores[places]
            if len(own) > k:
                cut = np.partition(own, len(own) - k)[len(own) - k]
                above, level = places[own > cut], places[own == cut]
                places = np.concatenate([above, level[: k - len(above)]])  # ids ascend, so ties keep the smaller ones
            out[0].extend([int(uids[row])] * len(places))
            out[1].extend([int(q_ids[row])] * len(places))
            out[2].extend(c_ids[places].tolist())
            out[3].extend(int(x) for x in scores[places])
        return pa.table([pa.array(x, pa.int64()) for x in out], names=["uid", "query_id", "vec_id", "score"])

    return run


def exact_topk(vectors: DataFrame, is_query, k: int = 5, scale: int = 256, vec_id: str = "vec_id", vector: str = "embedding", query_block: int = QUERY_BLOCK, tile_rows: int = TILE_ROWS) -> DataFrame:
    """(query_id, rank, vec_id, score) of each query's k best among all rows but its own. ``is_query`` is a column over vec_id."""
    rows = vectors.select(F.col(vec_id).cast("bigint").alias("vec_id"), F.transform(vector, lambda x: x.cast("double")).alias("vector"))
    rows = rows.where(F.col("vec_id").isNotNull() & F.col("vector").isNotNull() & F.forall("vector", lambda x: x.isNotNull() & ~F.isnan(x) & (F.abs(x) < float("inf"))))
    rows = rows.withColumn("uid", F.monotonically_increasing_id()).withColumn("asks", is_query)
    size = rows.agg(F.count("*").alias("n"), F.count_if("asks").alias("q")).first()
    blocks, tiles = max(1, -(-size["q"] // query_block)), max(1, -(-size["n"] // tile_rows))
    # few blocks would leave cores idle: more, smaller tiles cost only copies of the queries
    tiles = max(tiles, min(64, -(-size["n"] // 256)))
    asked = rows.where("asks").withColumn("block", F.pmod(F.xxhash64("uid"), F.lit(blocks))).withColumn("tile", F.explode(F.sequence(F.lit(0), F.lit(tiles - 1)).cast("array<bigint>")))
    spread = rows.withColumn("tile", F.pmod(F.xxhash64("uid", "vec_id"), F.lit(tiles))).withColumn("block", F.explode(F.sequence(F.lit(0), F.lit(blocks - 1)).cast("array<bigint>")))
    best = (
        asked.select("block", "tile", "uid", "vec_id", "vector").groupBy("block", "tile")
        .cogroup(spread.select("block", "tile", "vec_id", "vector").groupBy("block", "tile"))
        .applyInArrow(_score_tile(scale, k), "uid bigint, query_id bigint, vec_id bigint, score bigint")
    )
    order = Window.partitionBy("uid").orderBy(F.desc("score"), "vec_id")
    return best.withColumn("rank", F.row_number().over(order)).where(F.col("rank") <= k).select("query_id", "rank", "vec_id", "score")


def op4_term_at_a_time_topk(spark, sf_dir: str) -> DataFrame:
    return exact_topk(spark.read.parquet(f"{sf_dir}/embeddings.parquet"), F.col("vec_id") % 50 == 0)


SQL = """
WITH e AS (SELECT vec_id, row_number() OVER () AS r, list_transform(embedding, lambda x: floor(256 * x::DOUBLE)) AS v FROM embeddings
WHERE vec_id IS NOT NULL AND embedding IS NOT NULL AND len(list_filter(embedding, lambda x: x IS NULL OR NOT isfinite(x::DOUBLE))) = 0),
s AS (SELECT q.r, q.vec_id AS query_id, c.vec_id, list_inner_product(q.v, c.v)::BIGINT AS score FROM e q JOIN e c ON q.vec_id % 50 = 0 AND q.vec_id <> c.vec_id),
k AS (SELECT *, row_number() OVER (PARTITION BY r ORDER BY score DESC, vec_id) AS rank FROM s)
SELECT query_id, rank::INTEGER AS rank, vec_id, score FROM k WHERE rank <= 5
"""
