"""Connected components of a graph given by its edges."""

from __future__ import annotations

from collections.abc import Iterator

import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F
from pyspark.sql import types as T

from ..sources.shared import written
from .skew import heavy_keys, spread_join

#: Nodes that a task holds at a time, and pairs up to which one task ends the work (some 30 MB).
TASK_NODES, LOCAL_PAIRS = 1_000_000, 200_000


def contracted(pairs: DataFrame) -> DataFrame:
    """(node, root): the components of what each task sees, each node with the smallest node of its component; map-only. The components of these pairs are those of the given ones."""
    kind = pairs.schema.fields[0].dataType
    schema = T.StructType([T.StructField("node", kind), T.StructField("root", kind)])

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        parent: dict = {}

        def find(x):
            while parent[x] != x:
                parent[x] = x = parent[parent[x]]
            return x

        def out(of: pa.DataType) -> pa.RecordBatch:
            return pa.RecordBatch.from_arrays([pa.array(list(parent), of), pa.array([find(x) for x in list(parent)], of)], names=["node", "root"])

        of = None
        for b in batches:
            of = b.column(0).type
            for x, y in zip(b.column(0).to_pylist(), b.column(1).to_pylist(), strict=True):
                parent.setdefault(x, x)
                parent.setdefault(y, y)
                low, high = sorted((find(x), find(y)))
                parent[high] = low
            if len(parent) > TASK_NODES:
                yield out(of)
                parent.clear()
        if parent:
            yield out(of)

    return pairs.mapInArrow(run, schema)


def connected_components(edges: DataFrame, src: str = "src", dst: str = "dst") -> DataFrame:
    """(node, root): root is the smallest node that can be reached. Nodes are those of the edges.

    Each task first joins up the edges it holds, which leaves stars. Where few
    pairs are left (counted: LOCAL_PAIRS), one task ends the work. Beyond, in
    rounds a node takes the smallest root among its neighbours' and then its
    root's root, so long chains shorten at doubling speed, until none changes;
    each round is a written table, so the plan doesn't grow. A node of very many
    edges and a root of very many nodes are the rule here (a star is what copies
    make): such keys are joined where their rows stand, see skew. The result is
    the same in either way.
    """
    given = edges.select(F.col(src).alias("a"), F.col(dst).alias("b")).where("a is not null and b is not null")
    stars = written(contracted(given))
    if stars.limit(LOCAL_PAIRS + 1).count() <= LOCAL_PAIRS:
        return written(contracted(stars.coalesce(1)))
    stars = stars.select(F.col("node").alias("a"), F.col("root").alias("b"))
    both = written(stars.unionByName(stars.select(F.col("b").alias("a"), F.col("a").alias("b"))).distinct())
    hubs = written(heavy_keys(both, "b"))
    labels = written(both.groupBy("a").agg(F.min("b").alias("m")).select(F.col("a").alias("node"), F.least("a", "m").alias("root")))
    n = labels.count()
    while True:
        near = spread_join(both, labels.withColumnRenamed("node", "b"), "b", "inner", heavy=hubs).groupBy("a").agg(F.min("root").alias("m"))
        step = written(labels.join(near, labels.node == near.a).select("node", F.col("root").alias("old"), F.least("root", "m").alias("root")))
        jump = step.select(F.col("node").alias("root"), F.col("root").alias("further"))
        new = written(spread_join(step, jump, "root", "left", n).select("node", "old", F.least("root", F.coalesce("further", "root")).alias("root")))
        changed = new.where("root <> old").limit(1).count()
        labels = new.select("node", "root")
        if not changed:
            return labels
