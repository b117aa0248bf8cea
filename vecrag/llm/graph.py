"""Connected components of a links table: a bounded one in one task, others by min-label propagation with pointer jumping."""

from __future__ import annotations

from collections.abc import Iterator
from functools import partial

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from vecrag.llm.common import checkpointed

#: Links (16 bytes each) whose components one task finds: the rounds for more cost some 2000 tasks each at 211 partitions,
#: and the driver keeps a record of every task.
SMALL = 1 << 20


def contract(label: np.ndarray, a: np.ndarray, b: np.ndarray) -> None:
    """Give all that the links (a, b) join the smallest of their labels, in place; labels are places in `label`."""
    while len(a):
        top_a, top_b = label[a], label[b]
        low = np.minimum(top_a, top_b)
        for end in (top_a, top_b, a, b):
            np.minimum.at(label, end, low)
        while (label != (up := label[label])).any():
            label[:] = up
        apart = label[a] != label[b]
        a, b = a[apart], b[apart]


def _solved(schema: pa.Schema, batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
    held = [[c.to_numpy() for c in batch.columns] for batch in batches if batch.num_rows]
    if not held:
        return
    nodes, at = np.unique(np.concatenate([np.concatenate(x) for x in zip(*held, strict=True)]), return_inverse=True)
    label = np.arange(len(nodes))
    contract(label, *np.split(at, 2))
    yield pa.RecordBatch.from_arrays([pa.array(nodes), pa.array(nodes[label])], schema=schema)


def components(links: DataFrame, rounds: int = 64, small: int = SMALL) -> DataFrame:
    """(node, component) for every end of `links` (a, b): component is the smallest node reachable.

    Up to `small` links go to one task. With more, each round takes the smallest label among a node's neighbours, then the
    label of its label, so a path of length n needs about log n rounds. Labels and links stay distributed; each round is
    cut by checkpoint(). Rows with a null end link nothing.
    """
    both = links.select("a", "b").where("a is not null and b is not null and a <> b")
    if {kind for _, kind in both.dtypes} == {"bigint"} and small:
        both = checkpointed(both)
        if both.count() <= small:
            schema = pa.schema([("node", pa.int64()), ("component", pa.int64())])
            return checkpointed(both.coalesce(1).mapInArrow(partial(_solved, schema), "node long, component long"))
    both = checkpointed(both.unionByName(both.select(F.col("b").alias("a"), F.col("a").alias("b"))).distinct())
    labels = both.groupBy(F.col("a").alias("node")).agg(F.least(F.min("b"), F.first("a")).alias("component"))
    labels = checkpointed(labels)
    for _ in range(rounds):
        near = both.join(labels.select(F.col("node").alias("b"), "component"), "b").groupBy(F.col("a").alias("node")).agg(F.min("component").alias("low"))
        moved = labels.join(near, "node").select("node", F.least("component", "low").alias("component"), F.col("component").alias("before"))
        up = labels.select(F.col("node").alias("component"), F.col("component").alias("top"))
        moved = checkpointed(moved.join(up, "component", "left").select("node", F.least("component", F.coalesce("top", "component")).alias("component"), "before"))
        labels = moved.select("node", "component")
        if moved.where("component <> before").isEmpty():
            return labels
    raise RuntimeError(f"no fixpoint after {rounds} rounds")
