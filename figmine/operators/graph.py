"""Connected components of an undirected graph, as DataFrame rounds.

Each round lets every node take the smallest label among its neighbours and then jumps to that label's own label,
so long paths shrink by more than half a round. Rounds are cut by ``checkpoint`` into the shared folder, so a lost
executor costs a re-read and not the whole lineage; only the number of changed labels comes back to the driver.
"""

from __future__ import annotations

import tempfile

from pyspark.sql import DataFrame
from pyspark.sql import functions as F


def ensure_checkpoint_dir(spark) -> None:
    """Uses the cluster's ``spark.checkpoint.dir``; sets a temporary one only where none is set (tests)."""
    sc = spark.sparkContext
    if sc._jsc.sc().getCheckpointDir().isEmpty():
        sc.setCheckpointDir(sc._conf.get("spark.checkpoint.dir", None) or tempfile.mkdtemp(prefix="figmine-"))


def components(edges: DataFrame, src: str = "src", dst: str = "dst", max_rounds: int = 64) -> DataFrame:
    """(node, component): ``component`` is the smallest node id reachable. Nodes without an edge are not listed.

    Self loops, repeated and reversed edges change nothing; rows with a null end are ignored.
    """
    spark = edges.sparkSession
    ensure_checkpoint_dir(spark)
    pairs = edges.select(F.col(src).alias("a"), F.col(dst).alias("b")).where("a IS NOT NULL AND b IS NOT NULL")
    both = pairs.unionByName(pairs.select(F.col("b").alias("a"), F.col("a").alias("b"))).distinct().checkpoint()
    label = both.groupBy("a").agg(F.min("b").alias("low")).select(F.col("a").alias("node"), F.least("a", "low").alias("component")).checkpoint()
    for _ in range(max_rounds):
        near = (
            both.join(label.withColumnRenamed("node", "b"), "b")
            .groupBy("a")
            .agg(F.min("component").alias("near"))
        )
        stepped = label.join(near, label["node"] == near["a"]).select("node", "component", F.least("component", "near").alias("next"))
        jump = label.select(F.col("node").alias("next"), F.col("component").alias("far"))
        label = (
            stepped.join(jump, "next")
            .select("node", F.least("next", "far").alias("component"), (F.least("next", "far") != F.col("component")).alias("moved"))
            .checkpoint()
        )
        if not label.where("moved").limit(1).count():
            break
        label = label.drop("moved")
    else:
        raise RuntimeError(f"components did not settle in {max_rounds} rounds")
    return label.select("node", "component")
