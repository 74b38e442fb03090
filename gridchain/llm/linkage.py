"""Connected components, and links found inside buckets without forming all pairs of a bucket."""

from __future__ import annotations

from collections.abc import Callable, Iterator

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from gridchain.llm.shared import ids_of, release, stage, text_bytes, tidy, unstage, without_shuffles

#: Sets in a block of a long bucket; members of a bucket that is compared pair by pair.
BLOCK, SHORT = 1024, 32
#: Edges up to which one task finds the components: some 30 MB, whatever the input's size. More go through the rounds.
EDGES = 1 << 18


def _star(edges: DataFrame, large: bool) -> DataFrame:
    """Hang each node's larger (large) or smaller neighbours on the least node around it."""
    if large:
        around = edges.select("a", "b").union(edges.select(F.col("b").alias("a"), F.col("a").alias("b")))
    else:
        around = edges.select(F.greatest("a", "b").alias("a"), F.least("a", "b").alias("b"))
    least = around.groupBy("a").agg(F.least(F.min("b"), F.first("a")).alias("least"))
    joined = around.join(least, "a")
    if large:
        out = joined.filter("b > a").select(F.col("b").alias("a"), F.col("least").alias("b"))
    else:
        out = joined.select(F.col("b").alias("a"), F.col("least").alias("b")).union(least.select("a", F.col("least").alias("b")))
    return out.filter("a <> b").distinct()


def components(edges: DataFrame, limit: int = 60) -> DataFrame:
    """(node, component) of every node with an edge (a, b); component is its smallest node.

    Alternating large and small stars; each round is a staged table, so the driver sees
    only a row count and a checksum. Raises an error if `limit` rounds are too few.
    """
    held = stage(edges.filter("a <> b").select("a", "b").distinct(), "edges")
    known = None
    for _ in range(limit):
        spread = stage(_star(_star(held, True), False), "stars")
        with without_shuffles(edges.sparkSession):
            mark = spread.agg(F.count(F.lit(1)), F.sum(F.xxhash64("a", "b").cast("decimal(38,0)"))).first()
        unstage(held)
        held = spread
        if mark == known or mark[0] == 0:
            break
        known = mark
    else:
        raise RuntimeError(f"components did not converge in {limit} rounds")
    return held.select(F.col("a").alias("node"), F.col("b").alias("component")).union(held.select(F.col("b").alias("node"), F.col("b").alias("component"))).distinct()


def _least(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
    """(node, component) of the whole graph of edges (a, b), by hanging roots on smaller ones until nothing moves."""
    a, b = ([np.zeros(0, np.int64)] for _ in range(2))
    for batch in batches:
        a.append(ids_of(batch.column("a")))
        b.append(ids_of(batch.column("b")))
    nodes, ends = np.unique(np.concatenate([*a, *b]), return_inverse=True)
    x, y = np.split(ends, 2)
    root = np.arange(len(nodes))
    while len(x):
        least = np.minimum(root[x], root[y])
        for to in (root[x], root[y]):
            np.minimum.at(root, to, least)
        while (root[root] != root).any():
            root = root[root]
        apart = root[x] != root[y]
        x, y = x[apart], y[apart]
    for start in range(0, len(nodes), 1 << 16):
        part = slice(start, start + (1 << 16))
        yield pa.RecordBatch.from_arrays([pa.array(nodes[part]), pa.array(nodes[root[part]])], ["node", "component"])


def linked(links: DataFrame) -> DataFrame:
    """Staged (node, component) of staged links (a, b), as components() has them.

    Up to EDGES links one task takes them all: a round of components() costs six exchanges, however few they are.
    """
    if links.count() > EDGES:
        return stage(components(links), "components")
    return stage(links.filter("a <> b").select("a", "b").coalesce(1).mapInArrow(tidy(_least), "node long, component long"), "components")


def _mixed(members: DataFrame, found: DataFrame | None) -> DataFrame:
    """Members with their component, in buckets that hold more than one component."""
    if found is None:
        rows = members.withColumn("component", F.col("node"))
    else:
        rows = members.join(found, "node", "left").withColumn("component", F.coalesce("component", "node"))
    spans = rows.groupBy("bucket_key").agg(F.min("component").alias("low"), F.max("component").alias("high"), F.min_by("node", F.struct("weight", "node")).alias("plainest"), F.max("node").alias("last_node"))
    return rows.join(spans.filter("low < high"), "bucket_key").drop("low", "high")


def _block_links(percent: int):
    """Pairs of two blocks of sets, in different components, with enough in common."""

    def run(table: pa.Table) -> pa.Table:
        table = table.combine_chunks()
        block, nodes, sizes, part = (np.asarray(table.column(c)) for c in ("block", "node", "n", "component"))
        low, high = table.column("low")[0].as_py(), table.column("high")[0].as_py()
        data, cuts = text_bytes(table.column("tokens").chunk(0) if table.num_rows else pa.array([], pa.binary()))
        tokens = np.frombuffer(data.tobytes(), np.uint64)
        owner = np.repeat(np.arange(len(nodes)), np.diff(cuts) // 8)
        values, place, counts = np.unique(tokens, return_inverse=True, return_counts=True)
        several = counts > 1
        index = np.cumsum(several) - 1
        keep = several[place]
        owner, place = owner[keep], index[place[keep]]
        order = np.argsort(place, kind="stable")
        owner, place = owner[order], place[order]
        rows, columns = np.flatnonzero(block == low), np.flatnonzero(block == high)
        at = np.full((2, len(nodes)), -1)
        at[0, rows], at[1, columns] = np.arange(len(rows)), np.arange(len(columns))
        common = np.zeros((len(rows), len(columns)), np.float32)
        for start in range(0, int(several.sum()), 2048):
            a, b = np.searchsorted(place, [start, start + 2048])
            sides = []
            for side, height in ((0, len(rows)), (1, len(columns))):
                dense = np.zeros((height, 2048), np.float32)
                to = at[side, owner[a:b]]
                dense[to[to >= 0], place[a:b][to >= 0] - start] = 1
                sides.append(dense)
            common += sides[0] @ sides[1].T
        union = sizes[rows][:, None] + sizes[columns][None, :] - common
        x, y = np.nonzero((100 * common >= percent * union) & (part[rows][:, None] != part[columns][None, :]))
        x, y = rows[x], columns[y]
        return pa.table({"a": np.minimum(nodes[x], nodes[y]), "b": np.maximum(nodes[x], nodes[y])})

    return run


def _short_pairs(rest: DataFrame, short: int) -> DataFrame:
    """Pairs of members of short buckets, in different components, that meet often enough.

    A bucket gives at most short / 2 pairs for each member. Pairs are counted before any set
    is moved: one that meets less often than both its members' depths ask for can't be similar.
    """
    few = rest.filter(F.col("members") <= short).select("bucket_key", "node", "component", "depth")
    other = few.select("bucket_key", F.col("node").alias("b"), F.col("component").alias("b_component"), F.col("depth").alias("b_depth"))
    met = few.withColumnRenamed("node", "a").join(other, "bucket_key").filter((F.col("a") < F.col("b")) & (F.col("component") != F.col("b_component")))
    counted = met.groupBy("a", "b").agg(F.count(F.lit(1)).alias("met"), F.first(F.least("depth", "b_depth")).alias("needed"))
    return counted.filter("met >= needed").select("a", "b")


def _long_links(rest: DataFrame, sets: DataFrame, percent: int, short: int, block: int) -> DataFrame:
    """Similar pairs of members of long buckets, each bucket by itself, in pairs of blocks of about `block` sets.

    Of buckets with the same members one is compared. Only verified links leave a task.
    """
    many = rest.filter(F.col("members") > short)
    alike = many.groupBy("bucket_key").agg(F.count(F.lit(1)).alias("size"), F.sum(F.xxhash64("node").cast("decimal(38,0)")).alias("sum"))
    once = alike.groupBy("size", "sum").agg(F.min("bucket_key").alias("bucket_key")).select("bucket_key", F.ceil(F.col("size") / F.lit(block)).cast("int").alias("blocks"))
    dealt = many.select("bucket_key", "node", "component").join(once, "bucket_key").withColumn("block", F.pmod(F.xxhash64("node"), F.col("blocks")).cast("int"))
    dealt = dealt.withColumn("other", F.explode(F.sequence(F.lit(0), F.col("blocks") - 1)))
    dealt = dealt.withColumns({"low": F.least("block", "other"), "high": F.greatest("block", "other")})
    rows = dealt.select("bucket_key", "low", "high", "block", "node", "component").join(sets.select("node", "n", "tokens"), "node")
    grouped = rows.groupBy("bucket_key", "low", "high")
    return grouped.applyInArrow(_block_links(percent), "a long, b long").distinct()


def bucket_links(members: DataFrame, sets: DataFrame, verify: Callable[[DataFrame], DataFrame], percent: int, block: int = BLOCK, short: int = SHORT) -> DataFrame:
    """Components of the graph of all similar pairs that meet in enough buckets, as (node, component).

    members: bucket_key, node, weight, depth; sets: node, n (size of its set), tokens (the
    set's values that other nodes hold too). Two nodes are candidates if they share as many buckets as the
    smaller depth asks for. Two rounds compare members only with one member of their
    bucket, first the one of least weight; verify(pairs) keeps similar ones. What they
    join needs no further comparison. The exact rest, members of buckets that still hold several
    components, is compared pair by pair in buckets of at most `short` members, in blocks of sets in
    longer ones. Work grows with a bucket's own members, never with what buckets reach through each other.
    """
    links, found, spark = None, None, members.sparkSession
    members = members.select("bucket_key", "node", "weight", "depth")
    for leader in ("plainest", "last_node"):
        mixed = _mixed(members, found)
        pairs = mixed.filter(F.col("node") != F.col(leader)).select(F.least("node", leader).alias("a"), F.greatest("node", leader).alias("b")).distinct()
        new = stage(verify(pairs), "links")
        links = new if links is None else links.union(new)
        if not new.isEmpty():
            found = linked(links)
        del mixed, pairs, new
        release(spark)
    for step in ("short", "long"):
        mixed = stage(_mixed(members, found), "mixed")
        sizes = mixed.groupBy("bucket_key").agg(F.count(F.lit(1)).alias("members"))
        rest = mixed.join(sizes.filter(F.col("members") <= short if step == "short" else F.col("members") > short), "bucket_key")
        with without_shuffles(spark):
            none = rest.isEmpty()
        if none:
            unstage(mixed)
            continue
        new = stage(verify(_short_pairs(rest, short)) if step == "short" else _long_links(rest, sets, percent, short, block), "links")
        if not new.isEmpty():
            links = links.union(new)
            found = linked(links)
        unstage(mixed)
        del mixed, sizes, rest, new
        release(spark)
    return found if found is not None else spark.createDataFrame([], "node bigint, component bigint")
