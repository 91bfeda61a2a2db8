"""Merkle fixity audit of replicated web archives.

An archive file holds records one after the other; a record's bytes are its header lines and its body. Each record is
hashed, and the records that start in one range of ``range_bytes`` bytes form a leaf: the hash of (offset, id, digest)
in order of offset. Leaves are hashed in groups of ``fanout`` up to one root per file, and the files' roots up to one
root per replica. An audit compares two replicas from the root down and follows only the branches that differ; at the
leaves it compares record by record and names what is changed, missing, extra or moved.

Digests, not bodies, leave the scan: a record travels as id, length and hash. A tree node has at most ``fanout``
children and a leaf the records of one range, so no group grows with the input.

Nulls and edge cases: a null body or address counts as empty; a record with a null id is hashed like any other and is
compared by address; repeated ids are told apart by their order in the file; empty bodies are records of their header
only; an empty replica has no root, and everything of the other one is missing or extra; extra columns are ignored.
"""

from __future__ import annotations

from pyspark.sql import DataFrame, Window
from pyspark.sql import functions as F

from .common import stored

FANOUT = 16
RANGE_BYTES = 256 << 10
#: Records per archive file, by their number.
FILE_RECORDS = 1000
UNNUMBERED_FILES = 4096


def record_bytes(url, body):
    """A response record: header lines, an empty line, the body and the closing empty lines."""
    body = F.coalesce(body, F.lit("")).cast("binary")
    head = F.concat(F.lit("WARC/1.1\r\nWARC-Type: response\r\nWARC-Target-URI: "), F.coalesce(url, F.lit("")), F.lit("\r\nContent-Length: "), F.octet_length(body).cast("string"), F.lit("\r\n\r\n"))
    return F.concat(head.cast("binary"), body, F.lit("\r\n\r\n").cast("binary"))


def manifest(pages: DataFrame, page_id: str = "page_id", url: str = "url", body: str = "html", file_records: int = FILE_RECORDS) -> DataFrame:
    """(file, offset, length, record, copy, digest): where each record lies and what it hashes to."""
    raw = record_bytes(F.col(url), F.col(body))
    # records without a number are dealt to files below 0 by what they hold
    unnumbered = F.lit(-1) - F.pmod(F.xxhash64(url, body), F.lit(UNNUMBERED_FILES))
    rows = pages.select(F.coalesce(F.floor(F.col(page_id) / file_records), unnumbered).cast("bigint").alias("file"), F.col(page_id).alias("record"), F.octet_length(raw).cast("bigint").alias("length"), F.sha2(raw, 256).alias("digest"))
    order = Window.partitionBy("file").orderBy("record", "digest")
    before = order.rowsBetween(Window.unboundedPreceding, -1)
    rows = rows.withColumn("offset", F.coalesce(F.sum("length").over(before), F.lit(0)))
    return rows.withColumn("copy", F.row_number().over(Window.partitionBy("file", "record").orderBy("digest"))).select("file", "offset", "length", "record", "copy", "digest")


def _joined(order: str, *parts: str):
    """Hash of the ordered rows of a group."""
    row = F.struct(F.col(order), F.concat_ws(":", *[F.coalesce(F.col(p).cast("string"), F.lit("")) for p in parts]).alias("s"))
    return F.sha2(F.array_join(F.transform(F.array_sort(F.collect_list(row)), lambda r: r["s"]), "|"), 256)


def leaves(records: DataFrame, range_bytes: int = RANGE_BYTES) -> DataFrame:
    """(file, node, hash) of the ordered offset ranges."""
    return records.withColumn("node", F.floor(F.col("offset") / range_bytes).cast("bigint")).groupBy("file", "node").agg(_joined("offset", "offset", "record", "digest").alias("hash"))


def _level_up(nodes: DataFrame, keys: list[str], fanout: int) -> DataFrame:
    return nodes.withColumn("up", F.floor(F.col("node") / fanout).cast("bigint")).groupBy(*keys, F.col("up")).agg(_joined("node", "node", "hash").alias("hash")).select(*keys, F.col("up").alias("node"), "hash")


def tree(records: DataFrame, levels: int, file_levels: int, fanout: int = FANOUT, range_bytes: int = RANGE_BYTES) -> list[DataFrame]:
    """Levels from the leaves to the replica's root: (file, node, hash) inside files, then (file=-1, node, hash) over files."""
    # every level is written once: it is a small fraction of the one below, and the plan stays flat
    out = [stored(leaves(records, range_bytes), "op3-leaves")]
    for _ in range(levels):
        out.append(stored(_level_up(out[-1], ["file"], fanout), "op3-nodes"))
    top = out[-1].select(F.lit(-1).cast("bigint").alias("file"), F.col("file").alias("node"), "hash")
    for _ in range(file_levels):
        top = stored(_level_up(top, ["file"], fanout), "op3-roots")
        out.append(top)
    return out


def _levels(count: int, fanout: int) -> int:
    n = 0
    while fanout**n < count:
        n += 1
    return max(n, 1)


def _differing(a: DataFrame, b: DataFrame) -> DataFrame:
    keys = ["file", "node"]
    return a.join(b.withColumnRenamed("hash", "other"), keys, "full_outer").where(~F.col("hash").eqNullSafe(F.col("other"))).select(*keys)


def audit(left: DataFrame, right: DataFrame, fanout: int = FANOUT, range_bytes: int = RANGE_BYTES, visited: list | None = None) -> DataFrame:
    """(file, record, copy, status, offset, length) of what differs in ``right`` from ``left``; both are manifests.

    status: changed, missing, extra or moved (same bytes at another offset). ``visited`` takes, from the root down, the
    nodes compared at each level and how many there are.
    """
    left, right = stored(left, "op3-manifest"), stored(right, "op3-manifest")
    spans = left.unionByName(right).agg(F.max("offset").alias("o"), F.max("file").alias("f"), F.min("file").alias("low")).first()
    if spans["o"] is None:
        return left.select("file", "record", "copy", F.lit("").alias("status"), "offset", "length").limit(0)
    levels = _levels(spans["o"] // range_bytes + 1, fanout)
    file_levels = _levels(max(spans["f"] + 1, -spans["low"], 1), fanout)
    a, b = (tree(x, levels, file_levels, fanout, range_bytes) for x in (left, right))
    live = None
    for k in range(len(a) - 1, -1, -1):
        x, y = a[k], b[k]
        all_nodes = x
        if live is not None:
            # descend: only children of a branch that differs
            if k == levels:
                up = live.select(F.col("node").alias("up"))
                x, y = (t.withColumn("up", F.floor(F.col("file") / fanout).cast("bigint")).join(up, "up", "left_semi").drop("up") for t in (x, y))
            else:
                up = live.select("file", F.col("node").alias("up"))
                x, y = (t.withColumn("up", F.floor(F.col("node") / fanout).cast("bigint")).join(up, ["file", "up"], "left_semi").drop("up") for t in (x, y))
        live = stored(_differing(x, y), "op3-differing")
        if visited is not None:
            visited.append((x.count(), all_nodes.count()))
    inside = live.withColumnRenamed("node", "leaf")
    p, q = (t.withColumn("leaf", F.floor(F.col("offset") / range_bytes).cast("bigint")).join(inside, ["file", "leaf"], "left_semi").drop("leaf") for t in (left, right))
    keys = ["file", "record", "copy"]
    same = (F.col("l.file") == F.col("r.file")) & F.col("l.record").eqNullSafe(F.col("r.record")) & (F.col("l.copy") == F.col("r.copy"))
    both = p.alias("l").join(q.alias("r"), same, "full_outer")
    status = F.when(F.col("r.digest").isNull(), "missing").when(F.col("l.digest").isNull(), "extra").when(F.col("l.digest") != F.col("r.digest"), "changed").when(F.col("l.offset") != F.col("r.offset"), "moved")
    return both.withColumn("status", status).where("status IS NOT NULL").select(*[F.coalesce(f"l.{k}", f"r.{k}").alias(k) for k in keys], "status", F.coalesce("l.offset", "r.offset").alias("offset"), F.coalesce("l.length", "r.length").alias("length"))


def damaged(pages: DataFrame) -> DataFrame:
    """A replica with known and rare damage, for audits on one table: of the page numbers, every 2003rd (rest 5) has one
    byte of its body changed in place and every 4001st (rest 7) is lost, which moves what follows in its file."""
    flipped = F.concat(F.lit("\0"), F.expr("substring(html, 2)"))
    return pages.where("page_id IS NULL OR page_id % 4001 <> 7").withColumn("html", F.when((F.col("page_id") % 2003 == 5) & (F.col("html") != ""), flipped).otherwise(F.col("html")))


def op3_merkle_fixity_audit(spark, sf_dir: str) -> DataFrame:
    pages = spark.read.parquet(f"{sf_dir}/pages.parquet").select("page_id", "url", "html")
    found = audit(manifest(pages), manifest(damaged(pages)))
    return found.where("status <> 'moved'").select("record", "status", F.col("offset").cast("bigint").alias("offset"), "length")


SQL = r"""
WITH r AS (SELECT page_id, page_id // 1000 AS f, coalesce(html, '') = '' AS empty, strlen('WARC/1.1' || chr(13) || chr(10) || 'WARC-Type: response' || chr(13) || chr(10) || 'WARC-Target-URI: ' || coalesce(url, '') || chr(13) || chr(10) || 'Content-Length: ' || strlen(coalesce(html, ''))::VARCHAR) + 4 + strlen(coalesce(html, '')) + 4 AS length FROM pages),
o AS (SELECT page_id, length, empty, coalesce(sum(length) OVER (PARTITION BY f ORDER BY page_id ROWS BETWEEN UNBOUNDED PRECEDING AND 1 PRECEDING), 0) AS "offset" FROM r)
SELECT page_id AS record, CASE WHEN page_id % 4001 = 7 THEN 'missing' ELSE 'changed' END AS status, "offset"::BIGINT AS "offset", length::BIGINT AS length FROM o WHERE page_id % 4001 = 7 OR (page_id % 2003 = 5 AND NOT empty)
"""
