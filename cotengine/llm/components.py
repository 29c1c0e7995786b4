"""Connected components of an edge table by alternating star contractions.

Narrow rows only: every round is two shuffles of (long, long) pairs. A star's centre is a
minimum, so the group-wise step is a partial aggregate that no hot vertex can overload.
"""

from __future__ import annotations

from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from cotengine.llm.store import materialize


def _large_star(edges: DataFrame) -> DataFrame:
    both = edges.select("u", "v").union(edges.select(F.col("v").alias("u"), F.col("u").alias("v")))
    least = both.groupBy("u").agg(F.min("v").alias("m")).select("u", F.least("u", "m").alias("m"))
    return both.join(least, "u").where(F.col("v") > F.col("u")).select(F.col("v").alias("u"), F.col("m").alias("v")).where(F.col("u") != F.col("v")).distinct()


def _small_star(edges: DataFrame) -> DataFrame:
    down = edges.select(F.greatest("u", "v").alias("u"), F.least("u", "v").alias("v"))
    least = down.groupBy("u").agg(F.min("v").alias("m"))
    joined = down.join(least, "u")
    return joined.select(F.col("v").alias("u"), F.col("m").alias("v")).union(least.select("u", F.col("m").alias("v"))).where(F.col("u") != F.col("v")).distinct()


def components(edges: DataFrame, most_rounds: int = 60) -> DataFrame:
    """(u, v) long pairs, each a link → (node, root): the least vertex of each vertex's component.

    Vertices without an edge are not listed; self loops and repeated edges are allowed. The
    rounds stop when the edge set stops changing (its count and a checksum), and raise if
    ``most_rounds`` did not suffice, rather than return a part.
    """
    now = materialize(edges.where(F.col("u").isNotNull() & F.col("v").isNotNull() & (F.col("u") != F.col("v"))).select(F.greatest("u", "v").alias("u"), F.least("u", "v").alias("v")).distinct(), "edges")
    seen = None
    for _ in range(most_rounds):
        mark = now.agg(F.count("*"), F.sum(F.xxhash64("u", "v").cast("decimal(20,0)"))).first()
        if not mark[0] or mark == seen:
            break
        seen = mark
        now = materialize(_small_star(_large_star(now)), "edges")
    else:
        raise RuntimeError(f"components did not settle within {most_rounds} rounds")
    roots = now.select(F.col("u").alias("node"), F.col("v").alias("root"))
    return roots.union(now.select(F.col("v").alias("node"), F.col("v").alias("root")).distinct())


def verified(members: DataFrame, check, ddl_of_members: str, *, chunk: int = 256, bunch: int | None = None) -> DataFrame:
    """Verify the pairs within candidate groups, each pair in one task → (node, root, links).

    ``members``: node, comp, weight and what ``check`` needs (``ddl_of_members`` names its
    columns). A group of up to ``chunk`` members is one task. A larger one is cut in chunks by
    hash, and each pair of chunks is a task, so no task holds over twice ``chunk`` members and
    no pair is left out. Small groups are handed over together, up to ``bunch`` members (``chunk`` if
    not given) of a batch at once. ``check(table, left, right,
    group)`` returns, over the table's rows, the links of each (weighted) and the least node
    each is connected to; only rows of one ``group`` may be linked, and ``left``/``right``
    mark the rows of the two chunks. ``links`` sums over tasks; roots of cut groups are joined up
    by ``components``. Members without a link come back with themselves as root.
    """
    from collections.abc import Iterator
    from itertools import chain

    import numpy as np
    import pyarrow as pa

    from cotengine.llm.blocks import rows, schema_of

    sizes = members.groupBy("comp").agg(F.count("*").alias("size")).where("size > 1").select("comp", F.ceil(F.col("size") / chunk).cast("int").alias("chunks"))
    dealt = members.join(sizes, "comp").withColumn("own", F.pmod(F.xxhash64("node"), F.col("chunks")).cast("int"))
    dealt = dealt.withColumn("other", F.explode(F.sequence(F.lit(0), F.col("chunks") - 1)))
    dealt = dealt.withColumn("i", F.least("own", "other")).withColumn("j", F.greatest("own", "other")).drop("other")
    ddl = "node long, root long, links long, cut boolean"
    schema = schema_of(ddl)

    def task(table: pa.Table) -> pa.RecordBatch:
        nodes = table.column("node").to_numpy()
        _, one = np.unique(nodes, return_index=True)
        table = table.take(pa.array(np.sort(one))).combine_chunks()  # a repeated row of the input counts once
        own, comp = table.column("own").to_numpy(), table.column("comp").to_numpy()
        links, root = check(table, own == table.column("i")[0].as_py(), own == table.column("j")[0].as_py(), comp)
        return rows(schema, table.column("node").combine_chunks(), root, links, table.column("chunks").to_numpy() > 1)

    def bunches(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        """Whole groups, as many small ones at once as make up a bunch, or one part of a cut group."""
        together = max(chunk, bunch or 0)
        rest: list[pa.RecordBatch] = []
        for batch in chain(batches, [None]):
            table = pa.Table.from_batches([*rest, *([batch] if batch is not None else [])]) if rest or batch is not None else None
            if table is None or not table.num_rows:
                continue
            comp, i, j, chunks = (table.column(c).to_numpy() for c in ("comp", "i", "j", "chunks"))
            starts = np.flatnonzero(np.concatenate([[True], (comp[1:] != comp[:-1]) | (i[1:] != i[:-1]) | (j[1:] != j[:-1])]))
            ends = [*starts[1:].tolist(), len(comp)]
            if batch is not None:  # the last group may go on
                rest = table.slice(int(starts[-1])).to_batches()
                starts, ends = starts[:-1], ends[:-1]
            at = 0
            for x, y in zip(starts.tolist(), ends):
                if chunks[x] > 1 or y - at > together:
                    if x > at:
                        yield task(table.slice(at, x - at))
                    at = x
                    if chunks[x] > 1:
                        yield task(table.slice(x, y - x))
                        at = y
            if ends and ends[-1] > at:
                yield task(table.slice(at, ends[-1] - at))

    done = materialize(dealt.repartition("comp", "i", "j").sortWithinPartitions("comp", "i", "j").mapInArrow(bunches, ddl), "verified")
    cut = done.where("cut")
    small = done.where(~F.col("cut")).select("node", "root", "links")
    if cut.isEmpty():
        return small
    roots = components(cut.select(F.col("node").alias("u"), F.col("root").alias("v")))
    large = cut.groupBy("node").agg(F.sum("links").alias("links")).join(roots, "node", "left").select("node", F.coalesce("root", "node").alias("root"), "links")
    return small.union(large)


def least_connected(nodes, a, b):
    """Least node that each of ``nodes`` is connected to by the pairs of places (a, b)."""
    import numpy as np

    parent = list(range(len(nodes)))

    def top(x: int) -> int:
        while parent[x] != x:
            parent[x] = parent[parent[x]]
            x = parent[x]
        return x

    for x, y in zip(a.tolist(), b.tolist()):
        x, y = top(x), top(y)
        if x != y:
            if nodes[x] > nodes[y]:
                x, y = y, x
            parent[y] = x
    return np.array([nodes[top(x)] for x in range(len(nodes))], np.int64)
