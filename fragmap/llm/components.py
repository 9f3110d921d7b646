"""Connected components over an edge table, by alternating star contraction.

Edges that fit one small task (``SMALL``) are joined there at once: a round of contraction
is several exchanges whatever the number of edges, and each leaves files and task records
for every partition.
"""

from __future__ import annotations

from collections.abc import Iterator

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from fragmap.llm import common
from fragmap.llm.gray_index import merge

SMALL = 1 << 18


def _mark(edges: DataFrame) -> tuple:
    row = edges.agg(F.count("*"), F.sum(F.xxhash64("u", "v").cast("decimal(38,0)"))).first()
    return tuple(row)


def _joined(edges: DataFrame) -> DataFrame:
    """(node, root) of a bounded number of edges, in one task."""

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        common.begin("components")
        ends = [np.stack([c.to_numpy(zero_copy_only=False) for c in batch.columns]) for batch in batches]
        if ends:
            nodes, number = np.unique(np.concatenate(ends, axis=1), return_inverse=True)
            a, b = number.reshape(2, -1)
            label = np.arange(len(nodes))
            merge(label, a, b)
            yield pa.record_batch([pa.array(nodes), pa.array(nodes[label])], ["node", "root"])

    return edges.coalesce(1).mapInArrow(run, "node bigint, root bigint")


def connected_components(edges: DataFrame, u: str = "u", v: str = "v", max_rounds: int = 60, at_once: int = SMALL) -> DataFrame:
    """(node, root) for every node on an edge; root is the least node of its component.

    At most ``at_once`` edges are joined in one task. Of more, each round points neighbours at the least node around them, once over larger and
    once over smaller ones, until nothing moves: a logarithmic number of rounds. Minima
    are taken with partial aggregation, so the centre of a large star is no hot key.
    """
    edges = common.checkpoint(edges.select(F.greatest(u, v).alias("u"), F.least(u, v).alias("v")).where("u <> v"))
    if edges.count() <= at_once:
        return _joined(edges)
    edges = common.checkpoint(edges.distinct())
    before = _mark(edges)
    if before[0] <= at_once:
        return _joined(edges)
    for _ in range(max_rounds):
        if not before[0]:
            break
        both = edges.unionByName(edges.select(F.col("v").alias("u"), F.col("u").alias("v")))
        least = both.groupBy("u").agg(F.least(F.min("v"), F.first("u")).alias("m"))
        large = both.join(least, "u").where("v > u").select(F.col("v").alias("u"), F.col("m").alias("v")).where("u <> v").distinct()
        least = large.groupBy("u").agg(F.min("v").alias("m"))
        small = large.join(least, "u").select(F.explode(F.array(
            F.struct(F.col("u"), F.col("m").alias("v")), F.struct(F.col("v").alias("u"), F.col("m").alias("v"))
        )).alias("e")).select("e.u", "e.v").where("u <> v").distinct()
        edges = common.checkpoint(small)
        now = _mark(edges)
        if now == before:
            break
        before = now
    else:
        raise RuntimeError(f"components did not settle in {max_rounds} rounds")
    nodes = edges.groupBy("u").agg(F.min("v").alias("root")).select(F.col("u").alias("node"), "root")
    return nodes.unionByName(edges.select(F.col("v").alias("node"), F.col("v").alias("root")).distinct())
