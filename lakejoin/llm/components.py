"""Connected components over an edge table, by contraction.

One round maps every node to the least of itself and its neighbours and carries the edges over to what their ends are
mapped to; each component of the smaller graph stands for one of the larger. The first round goes by the nodes themselves,
which closes stars around their smallest member at once, later ones by another hash each, which about halves even a long path. A graph of at most
``SMALL`` edges is solved by one task: a bounded table, so that the usual small graph costs the driver three plans and not ten or more.
"""

from __future__ import annotations

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from .common import arrow_schema, dropped, released, ship, stored

#: Most edges that one task solves (16 bytes each).
SMALL = 1 << 18


def solve(a: np.ndarray, b: np.ndarray) -> tuple[np.ndarray, np.ndarray]:
    """The nodes of edges (a, b), ascending, and the smallest node of each one's component."""
    ids, at = np.unique(np.concatenate([a, b]), return_inverse=True)
    x, y = at[: len(a)], at[len(a) :]
    label = np.arange(len(ids))
    while True:
        p, q = label[x], label[y]
        if (p == q).all():
            return ids, ids[label]
        np.minimum.at(label, np.maximum(p, q), np.minimum(p, q))
        while (label != (up := label[label])).any():
            label = up


def _in_one_task(edges: DataFrame) -> DataFrame:
    ship(edges.sparkSession)
    ddl = "node bigint, root bigint"
    schema = arrow_schema(ddl)

    def run(batches):
        ends = [[np.zeros(0, np.int64)], [np.zeros(0, np.int64)]]
        for batch in batches:
            for k in range(2):
                ends[k].append(np.array(batch.column(k)))
        yield pa.RecordBatch.from_arrays([pa.array(x, pa.int64()) for x in solve(*map(np.concatenate, ends))], schema=schema)
        released()

    return edges.coalesce(1).mapInArrow(run, ddl)


def _moved(edges: DataFrame, turn: int) -> DataFrame:
    """(node, to): the least of a node and its neighbours, in the order of the turn."""
    key = lambda c: F.struct((F.col(c) if turn == 0 else F.xxhash64(c, F.lit(turn))).alias("by"), F.col(c).alias("id"))
    both = edges.select("a", "b").union(edges.select(F.col("b").alias("a"), F.col("a").alias("b")))
    least = both.select("a", key("b").alias("m")).groupBy("a").agg(F.min("m").alias("m"))
    return least.select(F.col("a").alias("node"), F.least(F.col("m"), key("a")).getField("id").alias("to"))


def components(edges: DataFrame, most_rounds: int = 60, small: int = SMALL) -> DataFrame:
    """(node, root), stored, for every node of ``edges`` (a, b); root is the smallest node of its component.

    Edges may repeat or run from a node to itself (such a node alone is not returned); an empty table gives none.
    """
    now, maps = stored(edges.where("a <> b").select("a", "b")), []
    while now.count() > small:
        if len(maps) == most_rounds:
            raise RuntimeError("components did not settle")
        moved = stored(_moved(now, len(maps)))
        to = lambda side: moved.select(F.col("node").alias(side), F.col("to").alias(f"to_{side}"))
        fewer = stored(now.join(to("a"), "a").join(to("b"), "b").where("to_a <> to_b").select(F.least("to_a", "to_b").alias("a"), F.greatest("to_a", "to_b").alias("b")).distinct())
        dropped(now)
        now = fewer
        maps.append(moved)
    found = stored(_in_one_task(now))
    dropped(now)
    if not maps:
        return found
    for moved in reversed(maps):
        last = found.select(F.col("node").alias("to"), "root")
        up = stored(moved.join(last, "to", "left").select("node", F.coalesce("root", "to").alias("root")))
        dropped(found, moved)
        found = up
    least = stored(found.groupBy("root").agg(F.min("node").alias("least")))
    out = stored(found.join(least, "root").select("node", F.col("least").alias("root")))
    dropped(found, least)
    return out
