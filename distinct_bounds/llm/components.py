"""Connected components of a graph in a table, by contraction.

Minima over a node's links are taken per task first. The two joins that move links to their
ends' roots do bring the links of a node to one key; they have two ids a row, and the engine
splits a key of many rows at run time as the other side has one row for it."""

from __future__ import annotations

import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from distinct_bounds.llm.common import map_arrow, materialize

#: Links that one task may hold; a graph that is or has become as small as that is finished in one.
MOST_LINKS = 500_000


def components(links: DataFrame, most_links: int = MOST_LINKS, most_rounds: int = 64) -> DataFrame:
    """(node, root) for every node of links(a, b); nodes of a component share a root.

    In each round every node joins its least neighbour or itself, by the nodes' own order in
    the first round (stars fall together at once) and by a fresh hash in each later one (so
    that chains shrink by a constant share as well), and links are drawn between the joined
    nodes. Minima are taken per task before the shuffle. What is left of the graph once it
    has no more than most_links links is joined in one task. Null ends are left out.
    """
    kind = links.schema["a"].dataType
    links = links.filter(F.col("a").isNotNull() & F.col("b").isNotNull() & (F.col("a") != F.col("b")))
    links = materialize(links.select("a", "b").distinct(), "links")
    steps: list[DataFrame] = []
    for round_ in range(most_rounds):
        if links.count() <= most_links:
            steps.append(materialize(joined_here(links), "joined"))
            break
        both = links.unionByName(links.select(F.col("b").alias("a"), F.col("a").alias("b")))
        rank = (lambda c: F.lit(0).cast("bigint")) if round_ == 0 else (lambda c, r=round_: F.xxhash64(c, F.lit(r)))
        least = both.groupBy("a").agg(F.min(F.struct(rank(F.col("b")).alias("r"), F.col("b").alias("n"))).alias("m"))
        own = F.struct(rank(F.col("a")).alias("r"), F.col("a").alias("n"))
        joined = materialize(least.select(F.col("a").alias("node"), F.least(F.col("m"), own)["n"].cast(kind).alias("root")), "joined")
        steps.append(joined)
        to_a = joined.select(F.col("node").alias("a"), F.col("root").alias("x"))
        to_b = joined.select(F.col("node").alias("b"), F.col("root").alias("y"))
        moved = links.join(to_a, "a").join(to_b, "b").filter(F.col("x") != F.col("y"))
        links = materialize(moved.select(F.least("x", "y").alias("a"), F.greatest("x", "y").alias("b")).distinct(), "links")
    else:
        raise RuntimeError(f"not contracted in {most_rounds} rounds")
    roots = steps[0]
    for joined in steps[1:]:
        step = joined.select(F.col("node").alias("_n"), F.col("root").alias("_r"))
        roots = roots.join(step, F.col("root") == F.col("_n"), "left").select("node", F.coalesce("_r", "root").alias("root"))
    return materialize(roots, "roots") if len(steps) > 1 else roots


def joined_here(links: DataFrame) -> DataFrame:
    """(node, root) of a graph that is known to be small, by union and find in one task; roots are least nodes."""
    from pyspark.sql.pandas.types import to_arrow_type

    kind = to_arrow_type(links.schema["a"].dataType)

    def work(batches):
        root: dict = {}

        def find(x):
            root.setdefault(x, x)
            while root[x] != x:
                root[x] = root[root[x]]
                x = root[x]
            return x

        for batch in batches:
            for a, b in zip(batch.column(0).to_pylist(), batch.column(1).to_pylist(), strict=True):
                low, high = sorted((find(a), find(b)))
                root[high] = low
        nodes = list(root)
        yield pa.RecordBatch.from_arrays([pa.array(nodes, kind), pa.array([find(x) for x in nodes], kind)], ["node", "root"])

    name = links.schema["a"].dataType.simpleString()
    return map_arrow(links.coalesce(1), work, f"node {name}, root {name}")
