"""Jump graphs: sparse shortcut edges over paths and trees.

There is one shortcut a node and a stretch of 4 B. Graphs of smaller stretch with more edges would not help an access, whose binary search takes as long.
A path shorter than the `capacity` that B comes from keeps the bound of the capacity.
"""

from __future__ import annotations

from collections.abc import Iterator

import pyarrow as pa
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from trieaccess import kernels as K


def path_edges(spark: SparkSession, n: int) -> DataFrame:
    return spark.range(1, n).select(F.col("id").alias("src"), (F.col("id") - 1).alias("dst"))


def path_jumps(spark: SparkSession, n: int) -> DataFrame:
    """The far edge of each node, clamped at 0."""
    B = K.block_size(n)
    reach = F.lit(B) * F.pow(F.lit(2), F.col("id") % B).cast("long")
    return spark.range(1, n).select(F.col("id").alias("src"), F.greatest(F.col("id") - reach, F.lit(0)).alias("dst"))


def route_hops(spark: SparkSession, n: int) -> DataFrame:
    """t, r, aligning steps, far edges, single edges for every pair r < t of a path: quadratic by definition, for small n."""
    B = K.block_size(n)

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for b in batches:
            for t in b.column(0).to_pylist():
                rows = [(t, r, *K.route_path(t, r, B)) for r in range(t)]
                yield pa.RecordBatch.from_arrays([pa.array(c, pa.int64()) for c in zip(*rows)], names=["t", "r", "align", "far", "single"])

    return spark.range(1, n).mapInArrow(run, "t long, r long, align long, far long, single long")


def not_spanned(edges: DataFrame, extra: DataFrame, k: int) -> DataFrame:
    """Pairs reachable by `edges` that are further than k apart with `extra` added; tests only."""
    spark = edges.sparkSession
    edges.createOrReplaceTempView("_e")
    edges.unionByName(extra).distinct().createOrReplaceTempView("_h")
    closure = "WITH RECURSIVE c(src, dst, d) MAX RECURSION LEVEL 10000 AS (SELECT src, dst, 1 FROM {0} UNION ALL SELECT c.src, e.dst, c.d + 1 FROM c JOIN {0} e ON c.dst = e.src{1}) SELECT DISTINCT src, dst FROM c"
    near = spark.sql(closure.format("_h", f" WHERE c.d < {k}"))
    return spark.sql(closure.format("_e", "")).exceptAll(near)


def tree_stretch(segs: DataFrame, B_capacity: int) -> DataFrame:
    """seq_id, seg_no, pairs, mean_hops, max_hops, bound: climbs in the trie of a segment from each of its phrases to an ancestor halfway and to the root's child."""

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for b in batches:
            for seq, no, text in zip(*(c.to_pylist() for c in b.columns)):
                symbols = K.to_symbols(text)
                p = K.base_parse(symbols)
                if not p.m:
                    continue
                store, hops = K.DenseStore(K.pack_dense(p, K.block_size(B_capacity)).tolist(), p.n, K.block_size(B_capacity)), []
                for t, d in enumerate(p.depth[1:].tolist(), 1):
                    for goal in {max(1, d // 2), 1}:
                        r = K.Reads()
                        store._climb(t, goal, r)
                        hops.append(r.total)
                yield pa.RecordBatch.from_pydict({"seq_id": pa.array([seq], pa.int64()), "seg_no": pa.array([no], pa.int32()), "pairs": pa.array([len(hops)], pa.int64()),
                                                  "mean_hops": pa.array([sum(hops) / len(hops)]), "max_hops": pa.array([max(hops)], pa.int64()), "bound": pa.array([4 * K.block_size(B_capacity)], pa.int64())})

    return segs.select("seq_id", "seg_no", "text").mapInArrow(run, "seq_id long, seg_no int, pairs long, mean_hops double, max_hops long, bound long")
